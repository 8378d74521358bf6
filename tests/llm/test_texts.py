"""Tokens, classifiers, languages, mixing, archives, URL lists, search and the pipeline."""

import hashlib
import math
import random
import re
import string
from collections import Counter, defaultdict
from datetime import date, timedelta

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from ringview.llm import langid, maxscore, mixing, quality, queries, sentencepiece, url_filter, warc
from ringview.llm.common import table_path, text_view

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _d string, score double"
TEXTS = ["Hello world", "", None, "  two  spaces ", "a\nb\tc", "naïve café 日本語 🙂 ñ", "x" * 300, "The quick brown fox. " * 400, "1234567 890", "  odd\r\n", "​zero​width", "‮rtl"]


def docs(spark, texts, lang="en", source="s"):
    return spark.createDataFrame([(i, t, lang, source, 0, "clash", None) for i, t in enumerate(texts)], SCHEMA)


@pytest.fixture(scope="module")
def library():
    """The library's own segmentation with the same pieces and scores."""
    import sentencepiece as sp
    from sentencepiece import sentencepiece_model_pb2

    m = sentencepiece_model_pb2.ModelProto()
    m.ParseFromString(open(sentencepiece.MODEL, "rb").read())
    m.trainer_spec.model_type = 1  # unigram
    return sp.SentencePieceProcessor(model_proto=m.SerializeToString())


def test_viterbi_finds_the_best_sum(library):
    rng = random.Random(1)
    texts = [t for t in TEXTS if t] + ["".join(rng.choice("abcdeé ü.,THEtheing") for _ in range(rng.randint(1, 60))) for _ in range(300)]
    e = sentencepiece.encoder(sentencepiece.MODEL)
    ids, ends = e.encode(texts)
    score = lambda x: sum(library.get_score(i) if not library.is_byte(i) else 0 for i in x)
    a = 0
    same = 0
    for t, b in zip(texts, ends, strict=True):
        mine, theirs = ids[a:b].tolist(), library.encode(t)
        same += mine == theirs
        assert sum(map(library.is_byte, mine)) == sum(map(library.is_byte, theirs))
        assert score(mine) == pytest.approx(score(theirs), rel=1e-5)  # ties may fall either way
        a = b
    assert same >= 0.98 * len(texts)


def test_tokens_round_trip(spark):
    got = {r["doc_id"]: r for r in sentencepiece.encode(docs(spark, TEXTS)).collect()}
    for i, t in enumerate(TEXTS):
        assert got[i]["round_trip"] and got[i]["n_tokens"] == len(got[i]["ids"]) and (bool(t) == bool(got[i]["ids"]))
    back = sentencepiece.decode(sentencepiece.encode(docs(spark, TEXTS))).collect()
    assert {r["doc_id"]: r["text"] for r in back} == {i: t or "" for i, t in enumerate(TEXTS)}
    assert sentencepiece.encode(docs(spark, [])).collect() == []


def test_cache_is_bounded(monkeypatch):
    monkeypatch.setattr(sentencepiece, "CACHE", 50)
    e = sentencepiece.Encoder(sentencepiece.Vocabulary(open(sentencepiece.MODEL, "rb").read()))
    rng = random.Random(2)
    for _ in range(20):
        texts = [" ".join("".join(rng.choice(string.ascii_lowercase) for _ in range(5)) for _ in range(30)) for _ in range(3)]
        ids, ends = e.encode(texts)
        assert e.v.decode(ids, ends) == texts
    assert len(e.index) <= 50 + 90


def held(i):
    import zlib

    return zlib.crc32(str(i).encode()) % 4 == 2


def test_quality(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 8)))
    texts, labels = [], []
    for i in range(300):
        bad = i % 3 == 0
        texts.append(" ".join(rng.choice(["$$$", "buy!!!", "###"]) if bad and rng.random() < 0.5 else word() for _ in range(60)))
        labels.append((i, int(not bad), 0))
    texts += [None, ""]
    d = docs(spark, texts)
    y = spark.createDataFrame(labels + [(None, 1, 0), (5, None, 0)], "doc_id long, quality int, toxic int")
    model = quality.fit(d, y)
    got = {r["_d"]: r["score"] for r in quality.score(d, model).collect()}
    assert len(got) == 302 and all(0 <= s <= 1 for s in got.values()) and got[300] == got[301]
    right = [(got[i] >= 0.7) == bool(q) for i, q, _ in labels if held(i)]
    assert sum(right) / len(right) > 0.95
    kept = quality.keep_good(d, model)
    assert kept.columns == d.columns and {r["doc_id"] for r in kept.collect()} == {i for i, s in got.items() if s >= 0.7}
    model2 = quality.fit(d, y.where("false"))
    assert {r["score"] for r in quality.score(d, model2).collect()} == {0.5}
    assert quality.score(docs(spark, []), model).collect() == []
    # held-out labels change nothing
    flipped = y.withColumn("quality", F.when(quality.held_out("doc_id"), 1 - F.col("quality")).otherwise(F.col("quality")))
    assert np.array_equal(quality.fit(d, flipped)[0], model[0])


def test_logits_equal_the_network():
    texts = ["one two two three", "", "é", "a b a b a b a b c", "x y"]
    data, at = text_view(pa.array(texts))
    scores = np.random.default_rng(1).normal(size=1 << 10).astype(np.float32)
    whole = quality.logits(scores, 0.5, data, at)
    for i, (rows, w) in enumerate(quality.bags(data, at, 10)):
        assert whole[i] == pytest.approx(float(w @ scores[rows]) + 0.5, rel=1e-5)
        one, ends = text_view(pa.array([texts[i]]))
        assert quality.logits(scores, 0.5, one, ends)[0] == pytest.approx(whole[i])


def test_language(spark, sf):
    d = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet")
    extra = spark.createDataFrame([(10**6, None, None, None, 0), (10**6 + 1, "123 ... !", "en", None, 0), (10**6 + 2, "", None, None, 0)], d.schema)
    d = d.unionByName(extra)
    got = {r["_d"]: r for r in langid.predict(d, langid.fit(d)).collect()}
    assert [got[10**6 + i]["lang_pred"] for i in range(3)] == ["und"] * 3 and all(0 <= r["score"] <= 1 for r in got.values())
    right = [got[r["doc_id"]]["lang_pred"] == r["lang"] for r in d.collect() if r["lang"] and held(r["doc_id"]) and r["doc_id"] < 10**6]
    assert sum(right) / len(right) > 0.97
    none = langid.predict(docs(spark, ["abc"]), langid.fit(docs(spark, [])))
    assert [(r["lang_pred"], r["score"]) for r in none.collect()] == [("und", 0.0)]
    alone = langid.predict(docs(spark, ["abc", "def"]), langid.fit(docs(spark, ["abc"] * 9)))
    assert {r["lang_pred"] for r in alone.collect()} == {"en"}


@pytest.mark.parametrize("k", [2, 3, 4, 5, 9, 30])
def test_codewords_correct_errors(k):
    code = langid.codewords(k)
    distance = min(int((code[i] != code[j]).sum()) for i in range(k) for j in range(i))
    assert distance >= max(1, code.shape[1] // 4) and len(np.unique(code, axis=0)) == k
    wrong = code.copy()
    wrong[:, : (distance - 1) // 2] *= -1  # fewer wrong bits than half the distance
    assert np.array_equal(langid.decode(wrong * 5, code)[0], np.arange(k))


def mixed_rows(spark):
    rng = random.Random(5)
    rows = []
    for s, n in [("a", 200), ("b", 3), ("é", 40), ("Z", 1), ("", 10), (None, 25), ("zero", 2)]:
        for _ in range(n):
            text = None if s == "zero" else " ".join("w" * rng.randint(1, 9) for _ in range(rng.randint(0, 60)))
            rows.append((len(rows), text, "en", s, 0, "x", None))
    rows += rows[:3]
    return rows


def water(sizes, weights, most=3):
    target, open_ = dict.fromkeys(sizes, 0.0), set(sizes)
    total = sum(sizes.values())
    capped = set()
    while True:
        left = total - sum(most * sizes[s] for s in capped)
        heavy = sum(weights[s] for s in open_)
        over = {s for s in open_ if left * weights[s] / heavy > most * sizes[s]} if heavy else set()
        if not over:
            for s in sizes:
                target[s] = most * sizes[s] if s in capped else left * weights[s] / heavy
            return target
        capped |= over
        open_ -= over


def test_mixing(spark, monkeypatch):
    monkeypatch.setattr(mixing, "STRETCH", 16)
    rows = mixed_rows(spark)
    d = spark.createDataFrame(rows, SCHEMA)
    got = mixing.mix(d.repartition(5)).collect()
    assert len(got) == len(rows)
    size = {r[0]: len(re.findall(r"[^\x20\x09-\x0D]+", r[1] or "")) for r in rows}
    total = defaultdict(int)
    for r in rows:
        total[r[3]] += size[r[0]]
    order = sorted(total, key=lambda s: (s is None, s or ""))
    want = water(dict(total), {s: (1, 2, 3)[i % 3] for i, s in enumerate(order)})
    taken = defaultdict(int)
    for r in got:
        s = r["source"]
        assert r["size"] == size[r["_d"]] and r["source_size"] == total[s] and r["target"] == pytest.approx(want[s])
        assert 0 <= r["taken"] <= 3 * r["size"]
        taken[s] += r["taken"]
    assert all(abs(taken[s] - want[s]) <= 1 for s in total)
    again = mixing.mix(d.repartition(2)).collect()
    assert Counter((r["_d"], r["taken"]) for r in got) == Counter((r["_d"], r["taken"]) for r in again)
    steps = mixing.training_order(d).collect()
    words = defaultdict(int)
    for r in steps:
        assert 0 <= r["position"] <= 1
        words[r["source"]] += r["words"]
    assert {s: n for s, n in words.items()} == {s: n for s, n in taken.items() if n}
    out = mixing.mixed_documents(d)
    assert out.columns == d.columns and out.count() == sum(2 * r["words"] >= r["size"] for r in steps)
    assert mixing.mix(spark.createDataFrame([], SCHEMA)).collect() == []


def test_positions_invert_demand(spark):
    schedule = [1.5, 1.0, 0.0, 2.0]
    shares = [i / 50 for i in range(51)]
    got = [r[0] for r in spark.createDataFrame([(s,) for s in shares], "s double").select(mixing.position(F.col("s"), F.array(*map(F.lit, schedule)))).collect()]
    t = np.linspace(0, 1, 300_001)
    weight = np.interp(t * 3, range(4), schedule)
    used = np.concatenate(([0], np.cumsum((weight[1:] + weight[:-1]) / 2)))
    assert np.allclose(np.interp(got, t, used / used[-1]), shares, atol=1e-4) and got == sorted(got)


PAGES = "page_id long, url string, html string, payload string, _d long"


def pages(spark):
    long = "<p>" + "é" * 60 + "</p>"
    rows = [(5, "http://a", long, None, 1), (3, "http://b\r\nX: y", long, None, 1), (9, None, long, None, 1), (1, "u", None, None, 1), (2, "u", "", None, 1), (4, "u", "short", None, 1), (6, "u", "short", None, 1), (7, "u", "x" * 100, None, 1), (8, "u", "x" * 99, None, 1), (10, "u", "x" * 99, None, 1), (None, "n", long, None, 1), (None, "n", "only" * 50, None, 1)]
    return rows + [rows[7], rows[11]]


def test_warc(spark):
    rows = pages(spark)
    path = table_path(spark, "archive")
    warc.write_archive(spark.createDataFrame(rows, PAGES).repartition(4), path)
    got = Counter((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in warc.read_records(spark, path).collect())
    by = defaultdict(list)
    for r in rows:
        by[(r[2] or "").encode()].append(r[0])
    want = Counter()
    for payload, ids in by.items():
        first = min((i for i in ids if i is not None), default=None)
        seen = False
        for i in sorted(ids, key=lambda i: (i is None, i or 0)):
            back = len(payload) >= 100 and seen
            seen = True
            want[(i, len(payload), hashlib.sha256(payload).hexdigest(), "revisit" if back else "response", first if back else None)] += 1
    assert got == want
    assert spark.read.parquet(f"{path}/payloads").count() == len(by)
    whole = warc.reconstruct(spark, path).collect()
    assert Counter((r["page_id"], bytes(r["payload"])) for r in whole) == Counter((r[0], (r[2] or "").encode()) for r in rows)
    for r in whole:
        head, _, block = bytes(r["record"]).partition(b"\r\n\r\n")
        fields = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
        assert int(fields["Content-Length"]) == len(block) - 4 and block.endswith(b"\r\n\r\n") and "X" not in fields
    empty = table_path(spark, "archive")
    warc.write_archive(spark.createDataFrame([], PAGES), empty)
    assert warc.read_records(spark, empty).collect() == []


def test_url_filter(spark):
    rng = random.Random(6)
    hosts = ["a.example.com", "example.com", "x.b.org", "b.org", "deep.a.b.c.d.e.f.org", "", "org"]
    start = date(2024, 1, 1)
    caps = [(i, None if i == 3 else f"https://user@{rng.choice(hosts).upper()}:80/{rng.choice(['en', 'De', ''])}/p?q#f", None if i == 4 else start + timedelta(rng.randrange(400)), "clash") for i in range(300)]
    caps += caps[:5]
    entries = [(rng.choice(["domain", "path"]), None, start + timedelta(rng.randrange(-50, 420)), rng.choice(["add", "add", "remove"])) for _ in range(150)]
    entries = [(k, rng.choice(hosts[:-2] + ["org"]) + ("/" + rng.choice(["en", "de", ""]) if k == "path" else ""), d, a) for k, _, d, a in entries] + [(None, "b.org", start, "add"), ("domain", "b.org", None, "add")]
    got = url_filter.filter_captures(spark.createDataFrame(caps, "page_id long, url string, fetched date, host string"), spark.createDataFrame(entries, url_filter.ENTRY_SCHEMA)).collect()
    assert len(got) == len(caps)
    by_id = {c[0]: c for c in caps}
    days = defaultdict(dict)
    for k, p, d, a in entries:
        if k and d:
            days[k, p][d] = days[k, p].get(d, True) and a == "add"
    for r in got:
        _, url, day, _ = by_id[r["page_id"]]
        m = re.match(r"https://user@([^:]*):80/([^/]*)/", url or "")
        h, s = (m[1].lower(), m[2].lower()) if m else ("", "")
        found = []
        if h and day:
            tries = [("domain", ".".join(h.split(".")[i:])) for i in range(len(h.split(".")))][-6:] + [("domain", h), ("path", f"{h}/{s}")]
            for key in set(tries):
                past = sorted(d for d in days.get(key, {}) if d <= day)
                if past and days[key][past[-1]]:
                    since = past[-1]
                    for d in reversed(past):
                        if not days[key][d]:
                            break
                        since = d
                    found.append((key, since))
        assert r["host"] == h and r["n_lists"] == len(found) and r["blocked"] == bool(found)
        assert r["since"] == min((s for _, s in found), default=None) and r["pattern"] == min(found, default=((None, None), None))[0][1]
    none = url_filter.filter_captures(spark.createDataFrame([], "page_id long, url string, fetched date"), spark.createDataFrame([], url_filter.ENTRY_SCHEMA))
    assert none.collect() == []


@pytest.mark.parametrize("shard,block", [(7, 3), (8192, 512)])
def test_top_k(spark, shard, block):
    rng = np.random.default_rng(7)
    rows = [(i, [float(x) for x in rng.normal(size=rng.integers(1, 9))], 0, "x") for i in range(150)]
    rows += [(i, rows[0][1], 0, "x") for i in range(150, 190)]
    rows += [(300, None, 0, "x"), (320, [1.0, None], 0, "x"), (340, [float("nan")], 0, "x"), (360, [float("inf")], 0, "x"), (380, [], 0, "x"), (None, [1.0], 0, "x"), (400, [1e12, -1e12], 0, "x"), (401, [-3e8], 0, "x")]
    got = maxscore.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int, v string"), k=20, shard=shard, block=block).collect()
    whole = {i: [math.floor(64 * x) for x in v] for i, v, *_ in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)}
    want = set()
    for q in whole:
        if q % 20 == 0:
            s = [(-sum(a * b for a, b in zip(whole[q], whole[c], strict=False)), c) for c in whole if c != q]
            want |= {(q, r, c, -x) for r, (x, c) in enumerate(sorted(s)[:20], 1)}
    assert {(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got} == want and len(got) == len(want)
    assert maxscore.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>")).collect() == []


def test_pipeline(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:4]:
        out = stage(spark, d, sf)
        assert out.columns == d.columns, name
        before, after = Counter(map(tuple, d.collect())), Counter(map(tuple, out.collect()))
        assert set(after) <= set(before)
        if name == "exact dedup":
            fold = lambda t: (t or "").translate(str.maketrans(string.ascii_uppercase, string.ascii_lowercase))
            best = {}
            for r in before:
                best[fold(r[1])] = max(best.get(fold(r[1]), r), r, key=lambda r: r[0])
            assert after == Counter(best.values())
        d = spark.createDataFrame(list(after.elements()), d.schema)
    last = corpus_pipeline.STAGES[4][1](spark, d, sf)
    assert last.count() == d.count()
    assert corpus_pipeline.run(spark, sf).count() > 0


def test_queries_name_every_operator():
    assert [q for q in queries.QUERIES if q.startswith("op")] == sorted((q for q in queries.QUERIES if q.startswith("op")), key=lambda q: int(q[2:].split("_")[0])) and len(queries.QUERIES) == 11


def test_quality_scores_do_not_follow_the_sample(spark):
    rng = random.Random(9)
    words = ["".join(rng.choice("abcdefghijklmnop") for _ in range(6)) for _ in range(30)]
    d = docs(spark, [" ".join(rng.choice(words) for _ in range(40)) for _ in range(4000)])
    y = spark.createDataFrame([(i, int(i % 8 > 0), 0) for i in range(4000)], "doc_id long, quality int, toxic int")  # no text tells them apart
    for sample in (5000, 1500, 300):  # no class, one class and both classes over the cap
        mean = quality.score(d, quality.fit(d, y, sample=sample)).where(quality.held_out("_d")).agg(F.avg("score")).first()[0]
        assert mean == pytest.approx(7 / 8, abs=0.06), sample


def test_url_filter_covers_subdomains_of_any_depth(spark):
    listed = [".".join("abcdefghijklmnop"[:n]) + ".org" for n in (1, 5, 6, 7, 12)]
    hosts = [f"{'x.' * k}{d}" for d in listed for k in (0, 1, 9)] + ["y.b.c.d.e.f.g.org", "z" + listed[3]]
    day = date(2024, 1, 1)
    caps = spark.createDataFrame([(i, f"http://{h}/", day) for i, h in enumerate(hosts)], "page_id long, url string, fetched date")
    got = {r["page_id"]: r for r in url_filter.filter_captures(caps, spark.createDataFrame([("domain", d, day, "add") for d in listed], url_filter.ENTRY_SCHEMA)).collect()}
    for i, h in enumerate(hosts):
        found = sorted(d for d in listed if h == d or h.endswith("." + d))
        assert got[i]["blocked"] == bool(found) and got[i]["n_lists"] == len(found) and got[i]["pattern"] == min(found, default=None), h


def test_mixing_query_is_in_training_order(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    out = queries.op8_mixing(spark, sf)
    got = [r for part in out.rdd.glom().collect() for r in part]
    taken = {r["_d"]: (r["size"], r["source_size"], r["target"], r["taken"]) for r in mixing.mix(d).collect()}
    assert {r["doc_id"]: (r["size"], r["source_size"], r["target"], r["taken"]) for r in got} == taken and len(got) == d.count()
    order = defaultdict(list)
    for r in sorted(mixing.training_order(d).collect(), key=lambda r: r["pass"]):
        order[r["_d"]].append(r["position"])
    assert all(r["positions"] == order.get(r["doc_id"], []) and bool(r["positions"]) == (r["taken"] > 0) for r in got)
    first = [r["positions"][0] if r["positions"] else 2.0 for r in got]
    assert first == sorted(first) and len(set(first)) > 100
