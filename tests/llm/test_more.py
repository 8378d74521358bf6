"""Further cases: independent versions of the classifiers, chains, recall on the given tables, odd columns and values."""

import itertools
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from ringview.llm import exact_dedup, langid, maxscore, mixing, quality, queries, sentencepiece, simhash, substring_dedup, warc
from ringview.llm.common import components, only_result, table_path

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
MASK = (1 << 64) - 1
BASE = 0x9E3779B97F4A7C55


def fold(text):
    return bytes(c + 32 if 65 <= c <= 90 else c for c in (text or "").encode())


def held(doc_id):
    return zlib.crc32(str(doc_id).encode()) % 4 == 2


# --- classifiers, told again in plain Python -----------------------------------------------------------------------------
def finalise(h):
    h ^= h >> 32
    h = h * 0xD6E8FEB86659FD93 & MASK
    h ^= h >> 29
    h = h * 0x9E3779B97F4A7C15 & MASK
    return h ^ h >> 32


def polynomial(b):
    return sum((c + 1) * pow(BASE, i, 1 << 64) for i, c in enumerate(b)) & MASK


def plain_features(text, bits):
    """Table rows of a text's words, pairs, repetitions and character n-grams."""
    raw, out, shift = fold(text), Counter(), 64 - bits
    spans = [m.span() for m in WORD.finditer(raw)]
    words = [polynomial(raw[a:b]) for a, b in spans]
    for w in words:
        out[finalise(w + 1 & MASK) >> shift] += 1
    for v, w in itertools.pairwise(words):
        out[finalise(v * 0x9FB21C651E98DF25 + w & MASK) >> shift] += 1
        out[2 + (v == w)] += 1
    seen = set()
    for i in range(len(spans) - quality.RUN + 1):
        run = raw[spans[i][0] : spans[i + quality.RUN - 1][1]]
        out[int(run in seen)] += 1
        seen.add(run)
    for n in quality.GRAMS:
        for i in range(len(raw) - n + 1):
            g = (int.from_bytes(raw[i : i + n], "big") + (n << 56)) * 0x9E3779B97F4A7C15 & MASK
            g ^= g >> 29
            out[(g * 0xD6E8FEB86659FD93 & MASK) >> shift] += 1
    return out


def test_quality_query_equals_plain_version(spark, sf):
    """The whole query again: which rows are learned from, features, training, calibration, scores."""
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect() if r["quality"] in (0, 1)}
    bags = {i: plain_features(t, quality.BITS) for i, t in docs.items()}
    allowed = [i for i in labels if not held(i)]
    by_hash = {r[0]: r[1] for r in spark.createDataFrame([(i,) for i in allowed], "i long").selectExpr("i", "xxhash64(i)").collect()}
    order = [i for i in sorted(allowed, key=lambda i: (by_hash[i], i)) if i in docs]
    assert max(Counter(labels[i] for i in allowed).values()) <= quality.SAMPLE
    bag = lambda c: (np.array(sorted(c), dtype=np.int64), np.array([c[k] for k in sorted(c)], dtype=np.float64) / max(1, sum(c.values())))
    texts = [bag(bags[i]) for i in order]
    y = np.array([labels[i] for i in order])
    scores, bias = quality.train([(f, w.astype(np.float32)) for f, w in texts], y)
    slope, shift = quality._calibrate(np.array([w @ scores[f] + bias for f, w in texts]), y)
    got = {r["doc_id"]: r for r in queries.op5_quality(spark, sf).collect()}
    assert set(got) == set(docs)
    for i, c in bags.items():
        f, w = bag(c)
        p = 1 / (1 + math.exp(-((w @ scores[f] + bias) * slope + shift)))
        assert got[i]["score"] == pytest.approx(p, abs=2e-3) and got[i]["held_out"] == held(i)
        assert got[i]["predicted"] == int(got[i]["score"] >= 0.7)


def plain_profile(text, bits):
    raw, out = fold(text), Counter()
    for n in langid.GRAMS:
        for i in range(len(raw) - n + 1):
            out[((int.from_bytes(raw[i : i + n], "big") + n) * 0x9E3779B1 & 0xFFFFFFFF) >> 32 - bits] += 1
    x = np.zeros(1 << bits)
    for k, c in out.items():
        x[k] = math.sqrt(c)
    return x / max(np.linalg.norm(x), 1e-9)


def test_language_query_equals_plain_version(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang").collect()
    allowed = [r for r in rows if r["lang"] is not None and not held(r["doc_id"])]
    by_hash = {r[0]: r[1] for r in spark.createDataFrame([(r["doc_id"],) for r in allowed], "i long").selectExpr("i", "xxhash64(i)").collect()}
    learned = sorted(allowed, key=lambda r: (by_hash[r["doc_id"]], r["doc_id"]))
    names = sorted({r["lang"] for r in learned})
    code = langid.codewords(len(names))
    index = np.array([names.index(r["lang"]) for r in learned])
    share = np.array([len(index) / (len(names) * (index == k).sum()) for k in range(len(names))], dtype=np.float32)
    x = np.array([plain_profile(r["text"], langid.BITS) for r in learned], dtype=np.float32)
    w, b = langid.train(x, code[index], share[index])
    got = {r["doc_id"]: r for r in queries.op9_language(spark, sf).collect()}
    assert set(got) == {r["doc_id"] for r in rows}
    for r in rows:
        margin = plain_profile(r["text"], langid.BITS) @ w + b
        loss = {n: sum(math.log1p(math.exp(-m * c)) for m, c in zip(margin, code[k], strict=True)) for k, n in enumerate(names)}
        best = min(loss, key=loss.get)
        if not any(c.isalpha() for c in r["text"] or ""):
            best = "und"
        elif sorted(loss.values())[1] - loss[best] < 1e-3:
            continue
        assert got[r["doc_id"]]["lang_pred"] == best and got[r["doc_id"]]["held_out"] == held(r["doc_id"])


def test_language_of_numerals_and_many_languages(spark):
    schema = "doc_id long, text string, lang string, source string"
    rows = [(i, f"word{i % 300} tongue{i % 300} " * 3, f"l{i % 300:03d}", None) for i in range(1500)]
    d = spark.createDataFrame(rows, schema)
    model = langid.fit(d, sample=4)
    assert len(model[0]) == 300
    odd = spark.createDataFrame([(1, "²½Ⅷ 12", None, None), (2, "a²", None, None), (3, None, None, None), (3, None, None, None), (4, rows[7][1] * 2000, None, None)], schema)
    got = sorted((r["_d"], r["lang_pred"]) for r in langid.predict(odd, model).collect())
    assert [g[1] == "und" for g in got] == [True, False, True, True, False]
    assert langid.predict(spark.createDataFrame([], schema), model).collect() == []


# --- chains ---------------------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("bits", [1, 2, 5])
def test_chains_decide_and_prune(bits):
    """From some start every prefix keeps its budget if and only if the whole distance does; most pairs fall early."""
    m, rng = bits + 1, np.random.default_rng(bits)
    x = rng.integers(0, 1 << 63, 4000, dtype=np.uint64)
    for i in range(0, 4000, 2):
        x[i] = sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 2 * bits + 1), replace=False))
    found = np.zeros(len(x), dtype=bool)
    for start in range(m):
        alive, left = simhash.chained(x, np.full(len(x), start), bits, m)
        found[alive] = True
        assert left == sorted(left, reverse=True) and left[0] < 0.7 * len(x) and len(left) == m
    assert np.array_equal(found, np.bitwise_count(x) <= bits)


# --- near duplicates --------------------------------------------------------------------------------------------------------
def shingle_sets(texts):
    return [{b" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set() for w in (WORD.findall(fold(t)) for t in texts)]


def truth(sets):
    """All pairs with a similarity of 0.8 or more, by an inverted index."""
    by = defaultdict(list)
    for i, s in enumerate(sets):
        for x in s:
            by[x].append(i)
    common = Counter(p for ids in by.values() for p in itertools.combinations(ids, 2))
    return [p for p, n in common.items() if 5 * n >= 4 * (len(sets[p[0]]) + len(sets[p[1]]) - n)]


def groups(ids, root):
    out = defaultdict(set)
    for i in ids:
        out[root[i]].add(i)
    return sorted(map(sorted, out.values()))


def test_recall_on_the_given_documents(spark, sf):
    d = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet")
    rows = d.select("doc_id", "text").collect()
    sets = shingle_sets([r["text"] for r in rows])
    pairs = truth(sets)
    got = {r["_d"]: r["root"] for r in simhash.similar_documents(d).collect()}
    linked = [got[rows[i]["doc_id"]] == got[rows[j]["doc_id"]] for i, j in pairs]
    assert len(pairs) > 50 and sum(linked) / len(linked) >= 0.99
    root = dict(zip(*components(np.array([p[0] for p in pairs]), np.array([p[1] for p in pairs])), strict=True))
    empty = [i for i, s in enumerate(sets) if not s]
    want = groups(range(len(rows)), {i: -1 if i in empty else root.get(i, i) for i in range(len(rows))})
    assert groups(range(len(rows)), {i: got[r["doc_id"]] for i, r in enumerate(rows)}) == want


@pytest.mark.parametrize("rounds,large,crowd", [(0, 16, 512), (2, 0, 8), (1, 16, 8)])
def test_ways_to_the_same_groups(spark, monkeypatch, rounds, large, crowd):
    """A crowd of texts around the bound: with and without leaders, by cluster and by key."""
    monkeypatch.setattr(simhash, "LARGE", large)
    rng = np.random.default_rng(9)
    texts = []
    for _ in range(120):
        w = [f"b{i}" for i in range(60)]
        for k in rng.integers(0, 60, rng.integers(0, 3)):
            w[k] = f"x{rng.integers(10**9)}"
        texts.append(" ".join(w))
    sets = shingle_sets(texts)
    pairs = truth(sets)
    root = dict(zip(*components(np.array([p[0] for p in pairs]), np.array([p[1] for p in pairs])), strict=True))
    d = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = {r["_d"]: r["root"] for r in simhash.similar_documents(d, rounds=rounds, crowd=crowd).collect()}
    assert groups(range(len(texts)), got) == groups(range(len(texts)), {i: root.get(i, i) for i in range(len(texts))})


# --- columns and values that clash or are odd ----------------------------------------------------------------------------------
ODD = "doc_id long, text string, lang string, source string, _d string, _h string, _all int, __rv_d string, __rv_h string, k struct<m: map<string, int>>"


def odd_rows():
    words = " ".join(f"w{i}" for i in range(120))
    texts = [None, "", "A b", "a B", words, words + " end", words, "long " * 50_000, words]
    return [(i, t, "en", "s", "x", "y", 1, "p", "q", ({"a": i},)) for i, t in enumerate(texts)] + [(4, words, "en", "s", "x", "y", 1, "p", "q", ({"a": 4},))] * 2


def test_clashing_names_and_nested_maps(spark):
    rows = odd_rows()
    d = spark.createDataFrame(rows, ODD).repartition(3)
    ids = Counter(r[0] for r in rows)
    assert Counter(r["_d"] for r in exact_dedup.find_copies(d).collect()) == ids
    stay = exact_dedup.deduplicate(d)
    assert stay.columns == d.columns and sorted(fold(r["text"]) for r in stay.collect()) == sorted({fold(r[1]) for r in rows})
    near = simhash.drop_similar(d)
    assert near.columns == d.columns and near.count() == 4  # without words, "a b", the two long ones with their copies
    assert Counter(r["_d"] for r in simhash.near_duplicates(d).collect()) == ids
    assert Counter(r["_d"] for r in substring_dedup.remove_repeats(d, digest_only=True).collect()) == ids
    assert Counter(r["_d"] for r in sentencepiece.encode(d).select("doc_id").withColumnRenamed("doc_id", "_d").collect()) == ids
    assert mixing.mixed_documents(d).columns == d.columns
    model = quality.fit(d, spark.createDataFrame([(1, 0), (4, 1)], "doc_id long, quality int"))
    assert Counter(r["_d"] for r in quality.score(d, model).collect()) == ids and quality.keep_good(d, model).columns == d.columns


def test_scores_beyond_64_bits(spark):
    rows = [(0, [1e12, 1.0]), (20, [1e12, -1.0]), (1, [1.0, 1.0])]
    with pytest.raises(Exception, match="a score leaves 64 bits"):
        maxscore.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    got = maxscore.top_k(spark.createDataFrame([rows[0], rows[2], (2, [-100.0, 3.0])], "vec_id long, embedding array<double>")).collect()
    assert [(r["vec_id"], r["score"]) for r in got] == [(1, 64**2 * (10**12 + 1)), (2, 64**2 * (3 - 10**14))]


def test_archive_refers_to_its_records(spark):
    long = "x" * 200
    rows = [(7, "http://a WARC-Type: response\u0085WARC-Record-ID: <urn:record:1:1>", long), (2, "http://b", long), (2, "http://b", long), (None, None, long), (3, "u" * 2_000_000, long + "y" * 3_000_000)]
    path = table_path(spark, "archive")
    warc.write_archive(spark.createDataFrame(rows, "page_id long, url string, html string"), path)
    fields = [dict(x.split(": ", 1) for x in bytes(r["header"]).decode().split("\r\n")[1:] if x) for r in warc.read_headers(spark, path).collect()]
    known = {f["WARC-Record-ID"] for f in fields}
    assert len(known) == len(rows) and sum("WARC-Refers-To" in f for f in fields) == 3
    assert all(f["WARC-Refers-To"] in known for f in fields if "WARC-Refers-To" in f)
    got = Counter((r["page_id"], r["record_type"], r["refers_to"]) for r in warc.read_records(spark, path).collect())
    assert got == Counter({(7, "revisit", 2): 1, (2, "revisit", 2): 1, (2, "response", None): 1, (None, "revisit", 2): 1, (3, "response", None): 1})


def test_tables_on_the_way_are_deleted(spark):
    from pathlib import Path

    from ringview.llm import common

    with only_result(spark) as keep:
        a = keep(common.materialize(spark.range(5), "on-the-way").where("id > 1"), "result")
        gone = [t for t in common._tables if "on-the-way" in t]
    assert a.count() == 3 and gone and not any(Path(t).exists() for t in gone)
