"""SimHash near-dedup with pigeonring filtering.

A fingerprint is 64 majority bits.  Its bits form a ring of m segments; if two fingerprints differ in at most t bits,
some segment starts a chain all of whose prefixes of l segments differ in at most l*t/m bits.  The index key is the
start segment, which has to agree when t < m, with one half of the next, of which one half agrees when 2t < 2m;
the chain condition prunes what shares a key before the full Hamming check.  Crowded keys are worked off without
listing their pairs: for t <= 2 fingerprints meet in their one-bit variants, else blocks of a key are compared with
each other and only a spanning forest of each block pair is kept.

Texts of a given Jaccard similarity are too far apart for one fingerprint of 64 bits (similar_documents): there several
independent fingerprints, each made of the smallest values of ROWS hash functions over the five-word shingles, bring
pairs together with a stated recall, and each pair is decided by its exact similarity.
"""

from __future__ import annotations

import functools
import math
from fractions import Fraction

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringview.llm.common import FOLD, SPACE, bit_counts, components, keyed, lean, materialize, mix, only_rows, slices, word_runs
from ringview.llm.components import connected_components

#: Fingerprints of a key that are compared with each other at once.
CROWD = 512
#: Hash functions of one fingerprint of shingles; share of the pairs at the least similarity that must meet in a key, and
#: share of them that the comparison of all smallest values may lose after that.
ROWS, RECALL, LOSS = 4, 0.9995, 1e-5
#: Rounds of comparison with leaders; members of a leader that one group of rows takes.
ROUNDS, SHARE = 2, 512
#: Bytes of rows that a task holds; crowds of a cluster that is compared as one; shingles that weigh as much as one text more.
HELD, LARGE, WEIGHT = 32 << 20, 16, 256
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turn(x: np.ndarray, k: int) -> np.ndarray:
    return (x << np.uint64(k)) | (x >> np.uint64(64 - k))


def xxh64(data: np.ndarray, start: np.ndarray, end: np.ndarray, seed: int = 42) -> np.ndarray:
    """XXH64 of many byte spans: those under 32 bytes all at once, the others one by one."""
    size = end - start
    out = np.empty(len(start), dtype=np.uint64)
    for i in np.flatnonzero(size >= 32):
        out[i] = xxhash.xxh64_intdigest(data[start[i] : end[i]].tobytes(), seed)
    short = np.flatnonzero(size < 32)
    if not len(short):
        return out
    padded = np.concatenate((data, np.zeros(8, np.uint8)))
    eight = np.ndarray(len(data) + 1, dtype="<u8", buffer=padded, strides=(1,))
    four = np.ndarray(len(data) + 5, dtype="<u4", buffer=padded, strides=(1,))
    at, left = start[short].copy(), size[short].copy()
    h = np.uint64(seed) + _P5 + left.astype(np.uint64)
    for _ in range(3):
        if not len(k := np.flatnonzero(left >= 8)):
            break
        h[k] = _turn(h[k] ^ (_turn(eight[at[k]] * _P2, 31) * _P1), 27) * _P1 + _P4
        at[k] += 8
        left[k] -= 8
    k = np.flatnonzero(left >= 4)
    h[k] = _turn(h[k] ^ (four[at[k]].astype(np.uint64) * _P1), 23) * _P2 + _P3
    at[k] += 4
    left[k] -= 4
    for j in range(3):
        k = np.flatnonzero(left > j)
        h[k] = _turn(h[k] ^ (padded[at[k] + j].astype(np.uint64) * _P5), 11) * _P1
    h ^= h >> np.uint64(33)
    h *= _P2
    h ^= h >> np.uint64(29)
    h *= _P3
    h ^= h >> np.uint64(32)
    out[short] = h
    return out


def single_spaced(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Folded bytes with one space for each run of white space, and start, end and row of the words in them."""
    start, end, row = word_runs(data, at)
    blank = SPACE[data]
    keep = ~blank
    keep[1:] |= ~blank[:-1]
    place = np.cumsum(keep) - 1
    text = FOLD[data[keep]]
    text[SPACE[text]] = 0x20
    return text, place[start] if len(start) else start, place[end - 1] + 1 if len(end) else end, row


def shingles(start: np.ndarray, end: np.ndarray, row: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Spans of ``width`` words of one row, repeats included; of a shorter row the whole."""
    n = len(start)
    if not n:
        return start, end, row
    last = np.minimum(np.arange(n) + width - 1, n - 1)
    whole = (np.arange(n) + width <= n) & (row[last] == row)
    head = np.concatenate(([True], row[1:] != row[:-1]))
    words = np.bincount(row)[row]
    few = head & (words < width)
    take = np.flatnonzero(whole | few)
    stop = np.where(few[take], take + words[take] - 1, last[take])
    return start[take], end[stop], row[take]


def majority(hashes: np.ndarray, row: np.ndarray, rows: int) -> np.ndarray:
    """A bit is 1 if it is set in over half the row's hashes; rows without hashes have 0.  ``row`` ascends."""
    out = np.zeros(rows, dtype=np.uint64)
    if len(hashes):
        first = np.flatnonzero(np.concatenate(([True], row[1:] != row[:-1])))
        n = np.diff(np.append(first, len(row)))
        bits = bit_counts(hashes, first) * 2 > n[:, None]
        out[row[first]] = np.packbits(bits, axis=1, bitorder="little").view("<u8")[:, 0]
    return out


def fingerprints(data: np.ndarray, at: np.ndarray, width: int = 3, seed: int = 42) -> np.ndarray:
    text, start, end, row = single_spaced(data, at)
    a, b, r = shingles(start, end, row, width)
    return majority(xxh64(text, a, b, seed), r, len(at) - 1)


def _distinct(hashes: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    order = np.lexsort((hashes, row))
    hashes, row = hashes[order], row[order]
    first = np.flatnonzero(np.concatenate(([True], (hashes[1:] != hashes[:-1]) | (row[1:] != row[:-1])))) if len(row) else row
    return hashes[first], row[first], np.diff(np.append(first, len(row)))


def bands(similarity: float, recall: float = RECALL) -> int:
    """Independent fingerprints of ROWS smallest values, of which one agrees with this probability at ``similarity``."""
    return 1 if similarity >= 1 else math.ceil(math.log(1 - recall) / math.log(1 - similarity**ROWS))


def least_common(similarity: float, n: int, loss: float = LOSS) -> int:
    """The largest number of equal smallest values, of ``n``, that a pair at ``similarity`` misses with at most ``loss``."""
    k, below = 0, 0.0
    while k < n and (below := below + math.comb(n, k) * similarity**k * (1 - similarity) ** (n - k)) <= loss:
        k += 1
    return k


def passages(data: np.ndarray, at: np.ndarray, functions: int, width: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of the set of a text's shingles: its size, a digest of two numbers, and its smallest value under each of so many
    hash functions.  Two sets have the same smallest value with the probability of their Jaccard similarity."""
    rows = len(at) - 1
    size, digest, low = np.zeros(rows, np.int64), np.zeros((rows, 2), np.uint64), np.zeros((rows, functions), np.uint64)
    h, r = shingle_sets(data, at, width)
    if len(h):
        first = np.flatnonzero(np.concatenate(([True], r[1:] != r[:-1])))
        own = r[first]
        size[own] = np.diff(np.append(first, len(r)))
        for j in range(2):
            digest[own, j] = np.add.reduceat(mix(h + np.uint64(2 * j + 1) * _P3), first)
        salt = mix(np.arange(1, 2 * functions + 1, dtype=np.uint64) * _P1)
        for j in range(functions):
            low[own, j] = np.minimum.reduceat((h ^ salt[2 * j]) * (salt[2 * j + 1] | np.uint64(1)), first)
    return size, digest, low


def shingle_sets(data: np.ndarray, at: np.ndarray, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes and their row, ascending by row and hash."""
    text, start, end, row = single_spaced(data, at)
    a, b, r = shingles(start, end, row, width)
    return _distinct(xxh64(text, a, b), r)[:2]


def _segments(m: int) -> list[tuple[int, int]]:
    edge = [64 * i // m for i in range(m + 1)]
    return list(zip(edge[:-1], edge[1:], strict=True))


def keys(fp: Column, bits: int, m: int) -> Column:
    """Index keys: start segment and a half of the next, with their place."""
    if bits >= m:
        raise ValueError("the start segment of a chain agrees only if there are more segments than bits")
    part, out = _segments(m), []
    pick = lambda a, b: F.shiftrightunsigned(fp, a).bitwiseAND(F.lit((1 << (b - a)) - 1))
    for i, (a, b) in enumerate(part):
        c, d = part[(i + 1) % m]
        half = (c + d) // 2
        for j, (x, y) in enumerate(((c, half), (half, d))):
            out.append(F.shiftleft(pick(a, b), y - x).bitwiseOR(pick(x, y)).bitwiseOR(F.lit((2 * i + j) << 56)))
    return F.array(*out)


def chained(x: np.ndarray, start: np.ndarray, bits: int, m: int) -> tuple[np.ndarray, list[int]]:
    """Which differences (XOR of two fingerprints) have a chain from segment ``start`` all of whose prefixes keep their
    proportional budget, as places, and how many were left after 1, 2, ... segments.  The last prefix is the whole ring,
    whose budget is ``bits``."""
    edge = _segments(m)
    low, mask = (np.array(e, dtype=np.uint64) for e in ([a for a, _ in edge], [(1 << (b - a)) - 1 for a, b in edge]))
    alive, total, left = np.arange(len(x)), np.zeros(len(x), np.int64), []
    for length in range(1, m + 1):
        k = (start[alive] + length - 1) % m
        total = total + np.bitwise_count((x[alive] >> low[k]) & mask[k])
        fits = total * m <= length * bits
        alive, total = alive[fits], total[fits]
        left.append(len(alive))
    return alive, left


def _grouped(work):
    """A mapInArrow function over rows sorted by (key, block pair): ``work`` gets some whole groups and each row's group."""

    @lean
    def run(batches):
        held: list[pa.RecordBatch] = []
        for batch in batches:
            held.append(batch)
            if sum(x.num_rows for x in held) >= 20_000 or sum(x.nbytes for x in held) >= HELD:
                yield from whole(held, False)
        yield from whole(held, True)

    def whole(held, last):
        if not (rows := sum(x.num_rows for x in held)):
            return
        t = pa.Table.from_batches(held).combine_chunks()
        g = [t.column(c).to_numpy() for c in ("key", "bi", "bj")]
        new = np.concatenate(([True], np.any([x[1:] != x[:-1] for x in g], axis=0)))
        start = np.flatnonzero(new)
        stop = rows if last else int(start[-1])  # the last group may go on
        rest = t.slice(stop).to_batches()
        held.clear()
        held.extend(rest)
        if stop:
            yield from work(t.slice(0, stop), np.cumsum(new[:stop]))

    return run


def _met(t: pa.Table, group: np.ndarray):
    """Pairs of rows of one group, a before b, by distance; of two blocks only pairs across: each block has its own turn."""
    side = t.column("b").to_numpy()
    cross = t.column("bi").to_numpy() != t.column("bj").to_numpy()
    alive = np.arange(len(group) - 1)
    for d in range(1, len(group)):
        alive = alive[alive + d < len(group)]
        alive = alive[group[alive] == group[alive + d]]
        if not len(alive):
            break
        own = ~cross[alive] | (side[alive] != side[alive + d])
        yield alive[own], alive[own] + d


def _bytes(t: pa.Table, name: str, kind: str) -> np.ndarray:
    return np.frombuffer(b"".join(t.column(name).to_pylist()), dtype=kind).reshape(t.num_rows, -1)


def _compare(bits: int, m: int, check_bits: int | None):
    """Links of each group as a forest.  A pair is followed along the chain that starts at its key's segment; if it breaks
    there, another key of the pair has the chain that does not."""

    def work(t, group):
        fp, node, start = t.column("fp").to_numpy().view(np.uint64), t.column("node").to_numpy(), (t.column("key").to_numpy() >> 56) // 2
        sig = _bytes(t, "sig", "<u8") if check_bits is not None else None
        us, vs, n = [], [], 0
        for a, b in _met(t, group):
            ok, _ = chained(fp[a] ^ fp[b], start[a], bits, m)
            a, b = a[ok], b[ok]
            if sig is not None and len(a):
                ok = np.bitwise_count(sig[a] ^ sig[b]).sum(axis=1) <= check_bits
                a, b = a[ok], b[ok]
            us.append(node[a])
            vs.append(node[b])
            n += len(a)
            if n > 200_000:
                us, vs = ([x] for x in reversed(components(np.concatenate(us), np.concatenate(vs))))
                n = len(us[0])
        if us:
            v, u = components(np.concatenate(us), np.concatenate(vs))
            yield pa.RecordBatch.from_arrays([pa.array(u[u != v]), pa.array(v[u != v])], names=["u", "v"])

    return _grouped(work)


def _cross_root(similarity: Fraction, least: int, similar=None):
    """A forest of the pairs of different roots whose sizes allow the similarity and that have ``least`` smallest values in
    common; with ``similar``, of those that it confirms from the sets."""

    def work(t, group):
        node, root, size = (t.column(c).to_numpy() for c in ("node", "root", "size"))
        sig = _bytes(t, "sig", "u1")
        sets = [np.frombuffer(x.as_buffer(), dtype="<u8") for x in t.column("set")] if similar else None
        us, vs, n = [], [], 0
        for a, b in _met(t, group):
            ok = (root[a] != root[b]) & (np.minimum(size[a], size[b]) * similarity.denominator >= np.maximum(size[a], size[b]) * similarity.numerator)
            a, b = a[ok], b[ok]
            ok = (sig[a] == sig[b]).sum(axis=1) >= least
            a, b = a[ok], b[ok]
            if sets is not None and len(a):
                ok = np.array([similar(sets[i], sets[j]) for i, j in zip(a.tolist(), b.tolist(), strict=True)], dtype=bool)
                a, b = a[ok], b[ok]
            us.append(node[a])
            vs.append(node[b])
            n += len(a)
            if n > 200_000:
                us, vs = ([x] for x in reversed(components(np.concatenate(us), np.concatenate(vs))))
                n = len(us[0])
        if n:
            v, u = components(np.concatenate(us), np.concatenate(vs))
            yield pa.RecordBatch.from_arrays([pa.array(u[u != v]), pa.array(v[u != v])], names=["u", "v"])

    return _grouped(work)


def at_least(similarity: Fraction):
    """Whether two sorted arrays of distinct numbers have this Jaccard similarity or more."""

    def similar(a: np.ndarray, b: np.ndarray) -> bool:
        if not len(a) or not len(b):
            return len(a) == len(b)
        both = int((a[np.minimum(np.searchsorted(a, b), len(a) - 1)] == b).sum())
        return both * similarity.denominator >= (len(a) + len(b) - both) * similarity.numerator

    return similar


def _toward_leader(least: int):
    """Rows of a text beside the leader of one of its keys: how many smallest values they share, if ``least`` or more."""

    @lean
    def run(batches):
        for batch in batches:
            t = pa.Table.from_batches([batch])
            common = (_bytes(t, "sig", "u1") == _bytes(t, "lsig", "u1")).sum(axis=1) if batch.num_rows else np.zeros(0, np.int64)
            keep = common >= least
            yield pa.RecordBatch.from_arrays([batch.column("u").filter(pa.array(keep)), batch.column("v").filter(pa.array(keep)), pa.array(common[keep].astype(np.int64))], names=["u", "v", "common"])

    return run


def _alike(similarity: Fraction):
    """Sets by group, the group's first one before its members: the members of at least this Jaccard similarity to it."""
    similar = at_least(similarity)

    @lean
    def run(batches):
        lead, of = None, None
        for batch in batches:
            us, vs = [], []
            for group, member, node, s in zip(*(batch.column(c).to_pylist() for c in ("group", "member", "node")), batch.column("set"), strict=True):
                own = np.frombuffer(s.as_buffer(), dtype="<u8")
                if not member:
                    lead, of = own, group
                    continue
                assert of == group and lead is not None
                if similar(lead, own):
                    us.append(group)
                    vs.append(node)
            yield pa.RecordBatch.from_arrays([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], names=["u", "v"])

    return run


def _deal(index: DataFrame, count: DataFrame, crowd: int) -> DataFrame:
    """Rows of the keys in ``count`` (with n, their number) in pairs of blocks of a key: bi, bj, and the row's own b."""
    shared = index.join(count, "key").withColumn("parts", F.ceil(F.col("n") / crowd).cast("int")).withColumn("b", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    dealt = shared.select("*", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("o"))
    dealt = dealt.withColumn("bi", F.least("b", "o")).withColumn("bj", F.greatest("b", "o")).drop("n", "parts", "o")
    return dealt.repartition("key", "bi", "bj").sortWithinPartitions("key", "bi", "bj", "node")


def _deal_roots(rows: DataFrame, crowd: int, weight: Column) -> DataFrame:
    """Rows (key, node, root, ...) of keys with several roots, in pairs of blocks of a key of about ``crowd`` by weight.
    The largest root of a key has blocks of its own, which do not meet each other: no pair of one root is needed."""
    per = rows.groupBy("key", "root").agg(F.sum(weight).alias("n")).groupBy("key").agg(F.max(F.struct("n", "root")).alias("top"), F.sum("n").alias("n"), F.count("*").alias("k")).where("k > 1")
    part = lambda n: F.ceil(n / crowd).cast("int")
    per = materialize(per.select("key", F.col("top.root").alias("major"), part(F.col("n") - F.col("top.n")).alias("few"), part(F.col("top.n")).alias("many")), "several")
    own = F.xxhash64("node")
    dealt = rows.join(per, "key").withColumn("major", F.col("root") == F.col("major"))
    dealt = dealt.withColumn("b", F.when(F.col("major"), F.col("few") + F.pmod(own, F.col("many"))).otherwise(F.pmod(own, F.col("few"))).cast("int"))
    dealt = dealt.select("*", F.explode(F.sequence(F.lit(0), F.when(F.col("major"), F.col("few")).otherwise(F.col("few") + F.col("many")) - 1)).alias("o"))
    dealt = dealt.withColumn("bi", F.least("b", "o")).withColumn("bj", F.greatest("b", "o")).drop("few", "many", "major", "o")
    return dealt.repartition("key", "bi", "bj").sortWithinPartitions("key", "bi", "bj", "node")


def link(nodes: DataFrame, bits: int, m: int | None = None, check_bits: int | None = None, crowd: int = CROWD) -> DataFrame:
    """Edges (u, v) with the components of the graph "differ in at most ``bits`` bits" (and, of ``sig``, in at most
    ``check_bits``).  ``nodes``: node long, fp long, sig binary, one row each, in the shared folder."""
    m = m or bits + 1
    index = nodes.select(F.explode(keys(F.col("fp"), bits, m)).alias("key"), "node", "fp", *(["sig"] if check_bits is not None else []))
    count = materialize(index.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "keys")
    variants = bits <= 2 and check_bits is None
    few = count.where(F.col("n") <= crowd) if variants else count
    edges = _deal(index, few, crowd).mapInArrow(_compare(bits, m, check_bits), "u long, v long")
    if variants:
        many = materialize(index.join(count.where(F.col("n") > crowd), "key", "left_semi").select("node", "fp").distinct(), "crowded")
        flips = F.array(F.lit(0).cast("long"), *[F.lit(1 << b if b < 63 else -(1 << 63)).cast("long") for b in range(64 * (bits > 0))])
        near = many.select("node", F.explode(F.transform(flips, lambda x: F.col("fp").bitwiseXOR(x))).alias("v"))
        if bits == 1:  # a step of one bit joins a fingerprint to a node, not two nodes to each other
            meet = near.join(many.select(F.col("node").alias("to"), F.col("fp").alias("v")), "v").select(F.col("to").alias("u"), F.col("node").alias("v"))
        else:
            meet = near.groupBy("v").agg(F.min("node").alias("u"), F.collect_list("node").alias("all")).where(F.size("all") > 1).select("u", F.explode("all").alias("v"))
        edges = edges.unionByName(meet.where("u <> v"))
    return edges


def _fingerprint_rows(width: int, seed: int):
    @lean
    def run(batches):
        for batch in batches:
            for part, data, at in slices(batch, "_t"):
                fp = fingerprints(data, at, width, seed).view(np.int64)
                yield pa.RecordBatch.from_arrays([part.column("_d"), part.column("_h"), pa.array(fp)], names=["_d", "_h", "fp"])

    return run


def _passage_rows(bands: int):
    @lean
    def run(batches):
        for batch in batches:
            for part, data, at in slices(batch, "_t", 1 << 18):
                size, digest, low = passages(data, at, bands * ROWS)
                key = np.repeat(np.arange(1, bands + 1, dtype=np.uint64)[None, :] * _P5, len(size), axis=0)
                for j in range(ROWS):
                    key = mix(key * _P2 + low[:, j::ROWS])
                key, each = key[size > 0], (size > 0) * bands
                keys = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(each))).astype(np.int32)), pa.array(key.reshape(-1).view(np.int64)))
                sig = pa.array([x.tobytes() for x in low.astype(np.uint8)], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column("_d"), part.column("_h"), pa.array(size), *(pa.array(np.ascontiguousarray(digest[:, j]).view(np.int64)) for j in range(2)), keys, sig], names=["_d", "_h", "size", "d0", "d1", "keys", "sig"])

    return run


@lean
def _set_rows(batches):
    for batch in batches:
        for part, data, at in slices(batch, "_t", 1 << 18):
            h, r = shingle_sets(data, at)
            edge = np.searchsorted(r, np.arange(len(at)))
            sets = [h[a:b].astype("<u8").tobytes() for a, b in zip(edge[:-1], edge[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([part.column("node"), pa.array(sets, pa.binary())], names=["node", "set"])


def near_duplicates(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", width: int = 3, bits: int = 2, seed: int = 42, crowd: int = CROWD, one_task: int = 1_000_000) -> DataFrame:
    """One row per document: _d, _h (its identity), fp long, component_id (smallest id reachable), links long.

    Fingerprints link at ``bits`` or fewer differing bits.  Null and wordless texts have fingerprint 0 and link like
    any other.  Null ids are passed over when the smallest is sought; a component of nothing else has null.  Repeated
    rows stay apart.  An empty table gives no row.  ``links`` counts the other documents with the same fingerprint.
    """
    if bits > 2:
        raise ValueError("over 2 bits need a check fingerprint: see link")
    found = materialize(keyed(docs, id_col, text_col).mapInArrow(_fingerprint_rows(width, seed), "_d long, _h long, fp long"), "fingerprints")
    nodes = materialize(found.groupBy("fp").agg(F.min("_d").alias("low"), F.count("*").alias("n")).withColumn("node", F.col("fp")), "nodes")
    root = materialize(connected_components(link(nodes, bits, crowd=crowd), one_task), "roots")
    named = nodes.join(root, "node", "left").withColumn("root", F.coalesce("root", "node"))
    low = materialize(named.groupBy("root").agg(F.min("low").alias("component_id")), "lows")
    group = named.join(low, "root").where("n > 1 or not component_id <=> low").select("fp", "component_id", "n")
    group = materialize(group, "groups")
    out = found.join(group, "fp", "left")
    return out.select("_d", "_h", "fp", F.when(F.col("n").isNull(), F.col("_d")).otherwise(F.col("component_id")).alias("component_id"), (F.coalesce("n", F.lit(1)) - 1).alias("links"))


def _with_simhash(rows: DataFrame, near: DataFrame) -> DataFrame:
    """A further key for the texts of a SimHash component: its smallest id; texts without words meet by equality only."""
    near = near.select(F.col("_d").alias("_e"), F.col("_h").alias("_g"), F.xxhash64(F.lit("simhash"), "component_id").alias("meet")).dropDuplicates(["_e", "_g"])
    shared = near.join(near.groupBy("meet").agg(F.count("*").alias("n")).where("n > 1").select("meet"), "meet")
    keyed_ = rows.join(shared, F.expr("_d <=> _e and _h = _g"), "left")
    keys = F.when(F.col("meet").isNull() | (F.col("size") == 0), F.col("keys")).otherwise(F.concat("keys", F.array("meet")))
    return keyed_.select("_d", "_h", "size", "d0", "d1", keys.alias("keys"), "sig")


def similar_documents(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", similarity: float = 0.8, recall: float = RECALL, crowd: int = CROWD, one_task: int = 1_000_000, rounds: int = ROUNDS) -> DataFrame:
    """One row per document: _d, _h, _n (row number), root (row number of its group), kept.

    Texts link if the Jaccard similarity of their sets of five-word shingles is ``similarity`` or more.  Candidates are the
    texts of each SimHash component (``near_duplicates``), and, as those miss most pairs close to the bound, pairs are found
    by equal fingerprints of few shingles (``recall`` of those at ``similarity``, more above it) and decided by the sets.  In each of some
    ``rounds`` a text is compared with the leader, of those of its fingerprints, that seems nearest: a group of many
    copies is then one root, and its pairs are never listed.  What the links so far leave in different groups is compared
    pair by pair inside tasks: first by size and smallest values, which gives clusters of texts that may link, then, cluster
    by cluster (a large one key by key), by the sets.  Only forests of links leave the tasks.  The smallest id of a group
    stays (null ids last).  Texts without words link with each other only.
    """
    n, exact = bands(similarity, recall), Fraction(str(similarity))
    least = least_common(similarity, n * ROWS)
    passed = keyed(docs, id_col, text_col).mapInArrow(_passage_rows(n), "_d long, _h long, size long, d0 long, d1 long, keys array<long>, sig binary")
    found = materialize(_with_simhash(passed, near_duplicates(docs, text_col, id_col, crowd=crowd, one_task=one_task)).withColumn("_n", F.monotonically_increasing_id()), "passages")
    one = F.min(F.struct("_n", "_d", "_h", "keys", "sig")).alias("one")
    nodes = materialize(found.groupBy("size", "d0", "d1").agg(one, F.count("*").alias("n")).select("size", "d0", "d1", "n", F.col("one._n").alias("node"), "one._d", "one._h", "one.keys", "one.sig"), "nodes")
    index = nodes.select(F.explode("keys").alias("key"), "node")
    shared = materialize(index.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), "keys")
    own = index.join(shared, "key").groupBy("node").agg(F.collect_list("key").alias("keys"))  # at most a key for each fingerprint
    live = materialize(nodes.select("node", "_d", "_h", "size", "sig").join(own, "node"), "live")
    text = keyed(docs, id_col, text_col).alias("t").join(live.select("node", "_d", "_h").alias("w"), F.expr("t._d <=> w._d and t._h = w._h")).select("w.node", "t._t")
    sets = text.mapInArrow(_set_rows, "node long, set binary")
    repeated = found.groupBy("_d", "_h").count().where("count > 1")
    sets = materialize(sets if repeated.isEmpty() else sets.dropDuplicates(["node"]), "sets")
    root: DataFrame | None = None

    def rooted() -> DataFrame:
        own_root = live.withColumn("root", F.col("node")) if root is None else live.join(root, "node", "left").withColumn("root", F.coalesce("root", "node"))
        return own_root.select("keys", "node", "size", "sig", "root")

    def by_key() -> DataFrame:
        return rooted().withColumn("key", F.explode("keys")).drop("keys")

    def links(pairs: DataFrame) -> DataFrame:
        per = pairs.groupBy("u").agg(F.ceil(F.count("*") / SHARE).cast("int").alias("parts"))
        member = pairs.join(per, "u").select(F.col("v").alias("node"), F.col("u").alias("group"), F.pmod(F.xxhash64("v"), F.col("parts")).cast("int").alias("part"), F.lit(True).alias("member"))
        lead = per.select(F.col("u").alias("node"), F.col("u").alias("group"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(False).alias("member"))
        roles = materialize(lead.unionByName(member), "roles")
        met = sets.join(roles, "node").repartition("group", "part").sortWithinPartitions("group", "part", "member")
        return materialize(met.select("group", "member", "node", "set").mapInArrow(_alike(exact), "u long, v long"), "links")

    edges: list[DataFrame] = []

    def follow(found_links: DataFrame) -> DataFrame:
        edges.append(found_links)
        return materialize(connected_components(functools.reduce(DataFrame.unionByName, edges), one_task), "roots")

    for turn in range(rounds):
        rows = by_key()
        first = F.min(F.struct(F.xxhash64("key", "node", F.lit(turn)).alias("x"), F.col("node").alias("u"), F.col("size").alias("lsize"), F.col("sig").alias("lsig"), F.col("root").alias("lroot"))).alias("l")
        lead = rows.groupBy("key").agg(first, F.min("root").alias("a"), F.max("root").alias("b")).where("a <> b").select("key", "l.u", "l.lsize", "l.lsig", "l.lroot")
        met = rows.join(materialize(lead, "leaders"), "key").where("root <> lroot").where(F.least("size", "lsize") * exact.denominator >= F.greatest("size", "lsize") * exact.numerator)
        near = met.select("u", F.col("node").alias("v"), "sig", "lsig").mapInArrow(_toward_leader(least), "u long, v long, common long")
        pairs = materialize(near.groupBy("v").agg(F.max(F.struct("common", "u")).alias("b")).select(F.col("b.u").alias("u"), "v"), "pairs")
        if pairs.isEmpty():
            break
        root = follow(links(pairs))
    shape = "u long, v long"
    maybe = materialize(_deal_roots(by_key(), crowd, F.lit(1)).mapInArrow(_cross_root(exact, least), shape), "maybe")
    cluster = materialize(connected_components(maybe, one_task).select("node", F.col("root").alias("cluster")), "clusters")
    large = materialize(cluster.groupBy("cluster").agg(F.count("*").alias("n")).where(F.col("n") > LARGE * crowd).select("cluster"), "large")
    small = cluster.join(large, "cluster", "left_anti").select("node", F.col("cluster").alias("key"))
    at = rooted().drop("keys").join(small, "node")
    if not large.isEmpty():
        at = at.unionByName(by_key().join(cluster.join(large, "cluster", "left_semi"), "node", "left_semi"))
    dealt = _deal_roots(at.join(sets, "node"), crowd, F.col("size") / WEIGHT + 1)
    last = materialize(dealt.mapInArrow(_cross_root(exact, least, at_least(exact)), shape), "links")
    if root is None or not last.isEmpty():
        root = follow(last)
    group = materialize(nodes.join(root, "node", "left").where("n > 1 or root is not null").select("size", "d0", "d1", F.coalesce("root", "node").alias("root")), "groups")
    named = materialize(found.join(group, ["size", "d0", "d1"], "left").select("_d", "_h", "_n", F.coalesce("root", "_n").alias("root")), "named")
    best = materialize(named.groupBy("root").agg(F.min(F.struct(F.col("_d").isNull().alias("x"), "_d", "_n")).alias("best"), F.count("*").alias("size")).where("size > 1"), "best")
    return named.join(best, "root", "left").select("_d", "_h", "_n", "root", F.coalesce(F.col("best._n") == F.col("_n"), F.lit(True)).alias("kept"))


def drop_similar(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", **how) -> DataFrame:
    """The rows of ``docs`` that stay, one of each group, with their own columns."""
    found = materialize(similar_documents(docs, text_col, id_col, **how), "similar")
    copies = found.groupBy("_d", "_h").agg(F.count("*").alias("_copies"), F.max("kept").alias("kept")).where("kept").drop("kept")
    return only_rows(docs, materialize(copies, "kept"), id_col, text_col)
