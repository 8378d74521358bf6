"""The pipeline's near-dedup stage goes through SimHash: its components are candidates, the exact similarity decides."""

import numpy as np

from ringview.llm import simhash

SCHEMA = "doc_id long, text string"


def test_components_of_fingerprints_are_candidates(spark, monkeypatch):
    words = [f"w{i}" for i in range(400)]
    rows = [(1, " ".join(words)), (2, " ".join([*words[:399], "end"])), (3, " ".join(f"u{i}" for i in range(50))), (4, None), (5, "")]
    d = spark.createDataFrame(rows, SCHEMA)
    calls, near = [], simhash.near_duplicates
    monkeypatch.setattr(simhash, "near_duplicates", lambda *a, **k: calls.append(1) or near(*a, **k))
    assert sorted(r["doc_id"] for r in simhash.drop_similar(d).collect()) == [1, 3, 4] and calls == [1]


def test_a_pair_that_only_simhash_brings_together(spark, monkeypatch):
    words = [f"w{i}" for i in range(400)]
    rows = [(1, " ".join(words)), (2, " ".join([*words[:399], "end"])), (3, " ".join(f"u{i}" for i in range(50)))]
    d = spark.createDataFrame(rows, SCHEMA)
    by_id = {r["_d"]: r["component_id"] for r in simhash.near_duplicates(d).collect()}
    assert by_id[1] == by_id[2] == 1 and by_id[3] == 3
    near = simhash.near_duplicates(d)
    passed = d.selectExpr("doc_id AS _d", "0L AS _h", "1L AS size", "0L AS d0", "0L AS d1", "array(doc_id) AS keys", "CAST('' AS binary) AS sig").drop("_h").join(near.select("_d", "_h"), "_d")
    keys = {r["_d"]: set(r["keys"]) for r in simhash._with_simhash(passed, near).collect()}
    assert len(keys[1] & keys[2]) == 1 and keys[3] == {3} and np.all([len(keys[i]) == 2 for i in (1, 2)])
