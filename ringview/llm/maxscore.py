"""Exact top-k inner products by MaxScore.

A vector's numbers are whole: floor(scale * x).  For a query each dimension is a term with a posting for each vector.
What some terms can add to a score has two upper bounds: the sum of the terms' largest contributions in the shard,
and the product of lengths (of the query's and the vectors' parts in these dimensions).  Terms are sorted by bound; the
largest group of the last ones that cannot reach the query's threshold, the k-th best score so far, is non-essential.
Only essential postings are traversed for the whole shard; the other terms are probed, largest bounds first, for the
vectors that are still competitive.  The threshold goes from shard to shard.

Shards stay in the task they are dealt to; blocks of queries, which are small, go to each group of shards.  The lists of
the groups are merged.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ringview.llm.common import lean, materialize

#: Vectors of a shard, queries of a block, shards of a group (one task holds a group's vectors), first vectors of a group
#: that give a first threshold.
SHARD, BLOCK, GROUP, PILOT = 8192, 128, 8, 1024
#: Non-essential terms that are probed before the competitive vectors are counted again.
STEPS = (4, 8, 16)
#: Relative allowance for rounding in lengths, which only bound what is computed exactly.
SLACK = 1e-4


def finite_vectors(vectors: DataFrame, vector_col: str, id_col: str) -> DataFrame:
    """(vec_id, d array<double>); without null ids, null vectors and vectors with a null or non-finite component."""
    d = F.transform(F.col(f"`{vector_col}`"), lambda x: x.cast("double"))
    fine = F.forall("d", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    v = vectors.select(F.col(f"`{id_col}`").cast("long").alias("vec_id"), d.alias("d")).where(F.col("vec_id").isNotNull() & F.col("d").isNotNull())
    return v.where(F.coalesce(fine, F.lit(False)))


def narrow(whole: np.ndarray) -> tuple[bytes, str]:
    """The smallest type that holds whole numbers given as doubles, and their bytes."""
    most = np.abs(whole).max(initial=0)
    kind = next((k for k, limit in (("<i1", 2**7), ("<i2", 2**15), ("<i4", 2**31)) if most < limit), "<f8")
    return whole.astype(kind).tobytes(), kind


def arithmetic(most: float) -> type:
    """The fastest type in which sums of products up to ``most`` in all are exact; Python's integers if there is no other."""
    return np.float32 if most < 2**23 else np.float64 if most < 2**52 else np.int64 if most < 2**62 else object


def largest(whole: np.ndarray) -> float:
    return max(float(whole.max(initial=0)), -float(whole.min(initial=0)))


class Shard:
    """Vectors (rows in ascending order of id), and their postings: for each dimension the numbers of all vectors."""

    def __init__(self, ids: np.ndarray, whole: np.ndarray):
        self.ids, self.whole, self.rows = ids, whole, None

    def prepare(self, kind: type) -> None:
        """Rows, postings, least and largest number of each dimension, in one type, and squared numbers and lengths."""
        if self.rows is None or self.rows.dtype != kind:
            self.rows = _as(self.whole, kind)
            self.postings = np.ascontiguousarray(self.rows.T)
            self.low, self.high = self.rows.min(axis=0), self.rows.max(axis=0)
            self.squares = np.square(self.postings.astype(kind if kind is np.float32 else np.float64))
            self.lengths = self.squares.sum(axis=0) * (1 + SLACK)


def _as(whole: np.ndarray, kind: type) -> np.ndarray:
    if kind is object and whole.dtype.kind == "f":
        out = np.empty(whole.shape, dtype=object)
        out.ravel()[:] = [int(x) for x in whole.ravel()]
        return out
    return whole.astype(kind)


class Best:
    """The k best (score, id) of one query so far, its own id left out."""

    def __init__(self, own: int, k: int):
        self.own, self.k = own, k
        self.ids, self.scores = np.zeros(0, np.int64), np.zeros(0, np.int64)

    @property
    def threshold(self):
        return self.scores[-1] if len(self.scores) >= self.k else None

    def add(self, ids: np.ndarray, scores: np.ndarray) -> None:
        if len(scores) > self.k:  # ties with the k-th stay until ids decide
            on = scores >= np.partition(scores, len(scores) - self.k)[len(scores) - self.k]
            ids, scores = ids[on], scores[on]
        ids, scores = np.concatenate((self.ids, ids)), np.concatenate((self.scores.astype(scores.dtype), scores))
        order = np.lexsort((ids, -scores))[: self.k] if scores.dtype != object else np.array(sorted(range(len(ids)), key=lambda i: (-scores[i], ids[i]))[: self.k], dtype=np.int64)
        self.ids, self.scores = ids[order], scores[order]


def search(shard: Shard, query: np.ndarray, best: Best) -> int:
    """Add a shard's best to a query's; returns how many numbers were read."""
    a, b = query * shard.low, query * shard.high
    order = np.argsort(np.minimum(a, b) - np.maximum(a, b), kind="stable")  # largest bounds first
    most = np.maximum(a, b)[order]
    left = np.append(np.cumsum(most[::-1])[::-1], 0)  # what the terms from each place on add at most
    square = np.append(np.cumsum(np.square(query[order].astype(float))[::-1])[::-1], 0) * (1 + SLACK)
    theta, essential = best.threshold, len(order)
    if theta is not None:
        out = (left < theta) | (np.sqrt(square * shard.lengths.max()) < theta)
        if out[0]:
            return 0
        essential = int(np.argmax(out)) if out.any() else essential
    first = order[:essential]
    part = query[first] @ shard.postings[first]
    read, at = essential * len(part), essential
    alive = np.arange(len(part))
    if theta is not None and at < len(order):
        length = shard.lengths - shard.squares[first].sum(axis=0)
        alive = np.flatnonzero((part + left[at] >= theta) & (part + np.sqrt(square[at] * np.maximum(length, 0)) >= theta))
        part, length = part[alive], length[alive]
    elif theta is not None:
        alive = np.flatnonzero(part >= theta)
        part = part[alive]
    steps = iter(STEPS)
    while at < len(order) and len(alive):
        rest = order[at : at + next(steps, len(order))]
        probed = shard.rows[np.ix_(alive, rest)]
        part = part + probed @ query[rest]
        read += probed.size
        at += len(rest)
        length = length - np.square(probed.astype(length.dtype)).sum(axis=1)
        on = (part + left[at] >= theta) & (part + np.sqrt(square[at] * np.maximum(length, 0)) >= theta)
        alive, part, length = alive[on], part[on], length[on]
    ids = shard.ids[alive]
    if len(own := np.flatnonzero(ids == best.own)):
        ids, part = np.delete(ids, own), np.delete(part, own)
    if len(ids):
        best.add(ids, part)
    return read


def search_group(shards: list[Shard], qids: np.ndarray, q: np.ndarray, k: int) -> list[Best]:
    """The best of a group of shards for each query of a block."""
    found = [Best(int(i), k) for i in qids]
    width = max([q.shape[1], *(s.whole.shape[1] for s in shards)])
    q = _wide(q, width)
    kind = arithmetic(largest(q) * max(largest(s.whole) for s in shards) * width)
    numbers = _as(q, kind)
    for s in shards:
        s.whole = _wide(s.whole, width)
        s.prepare(kind)
        for query, best in zip(numbers, found, strict=True):
            search(s, query, best)
    return found


def _wide(whole: np.ndarray, width: int) -> np.ndarray:
    return whole if whole.shape[1] == width else np.pad(whole, ((0, 0), (0, width - whole.shape[1])))


def _matrix(row: dict) -> tuple[np.ndarray, np.ndarray]:
    kind = np.dtype(row["kind"])
    return np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["nums"], kind).reshape(row["n"], -1)


_PACKED = "n long, ids binary, nums binary, kind string"


def _pack(size: int, scale: int):
    """Rows (vec_id, d) to packed rows of ``size`` vectors."""

    def emit(ids, vs):
        width = max(1, max((len(x) for x in vs), default=1))
        m = np.zeros((len(vs), width))
        for i, x in enumerate(vs):
            m[i, : len(x)] = x
        whole = np.floor(m * scale)
        if not np.isfinite(whole).all():
            raise ValueError(f"a component times {scale} leaves the range of doubles")
        order = np.argsort(ids, kind="stable")
        nums, kind = narrow(whole[order])
        return pa.RecordBatch.from_arrays([pa.array([len(ids)]), pa.array([np.array(ids, dtype="<i8")[order].tobytes()], pa.binary()), pa.array([nums], pa.binary()), pa.array([kind])], names=["n", "ids", "nums", "kind"])

    def run(batches):
        ids, vs = [], []
        for batch in batches:
            ids += batch.column("vec_id").to_pylist()
            flat = batch.column("d")
            ends = flat.offsets.to_numpy()
            data = flat.values.to_numpy(zero_copy_only=False)
            vs += [data[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)]
            while len(ids) >= size:
                yield emit(ids[:size], vs[:size])
                ids, vs = ids[size:], vs[size:]
        if ids:
            yield emit(ids, vs)

    return run


def _search(k: int):
    """Rows by task, shards before blocks of queries; each block meets all shards of its task."""

    @lean
    def run(batches):
        shards, task = [], None
        for batch in batches:
            for row in batch.to_pylist():
                if row["task"] != task:
                    shards, task = [], row["task"]
                ids, whole = _matrix(row)
                if not row["query"]:
                    if not shards and len(ids) > 2 * PILOT:
                        shards.append(Shard(ids[:PILOT], whole[:PILOT]))
                        ids, whole = ids[PILOT:], whole[PILOT:]
                    shards.append(Shard(ids, whole))
                elif shards:
                    found = [b for b in search_group(shards, ids, whole, k) if len(b.ids)]
                    scores = [int(x) for b in found for x in b.scores]
                    if any(not -(2**63) <= x < 2**63 for x in scores):
                        raise ValueError("a score leaves 64 bits")
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.repeat([b.own for b in found], [len(b.ids) for b in found]).astype(np.int64)), pa.array(np.concatenate([b.ids for b in found]) if found else np.zeros(0, np.int64)), pa.array(scores, pa.int64())],
                        names=["query_id", "vec_id", "score"],
                    )

    return run


def top_k(vectors: DataFrame, k: int = 20, every: int = 20, vector_col: str = "embedding", id_col: str = "vec_id", scale: int = 64, shard: int = SHARD, block: int = BLOCK, group: int = GROUP) -> DataFrame:
    """(query_id, rank, vec_id, score): for each id divisible by ``every`` the ``k`` largest inner products with all other
    rows, ties to the smaller id.

    Rows with a null id or vector, or a null or non-finite component, take no part; shorter vectors count as padded
    with zeros.  Arithmetic is exact for components of any size; a reported score that leaves 64 bits is an error.  Of
    rows with one id each is a candidate of its own; a query is answered once for each id, by its largest row, and rows
    with its id are no candidates.
    """
    spark = vectors.sparkSession
    v = finite_vectors(vectors, vector_col, id_col)
    data = materialize(v.mapInArrow(_pack(shard, scale), _PACKED), "shards")
    queries = v.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.max("d").alias("d"))
    packed = materialize(queries.coalesce(max(1, spark.sparkContext.defaultParallelism)).mapInArrow(_pack(block, scale), _PACKED), "queries")
    # tasks: groups of shards, times parts of the queries where there are fewer groups than cores
    groups = max(1, math.ceil((data.agg(F.sum("n")).first()[0] or 0) / (shard * group)))
    parts = max(1, min(packed.count(), math.ceil(3 * spark.sparkContext.defaultParallelism / groups)))
    each = lambda n, at: F.explode(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), at)).alias("task")
    number = lambda n: F.pmod(F.xxhash64("ids"), F.lit(n)).cast("int")
    shards = data.select("*", F.lit(False).alias("query"), number(groups).alias("at")).select(*data.columns, "query", each(parts, lambda i: F.col("at") * parts + i))
    blocks = packed.select("*", F.lit(True).alias("query"), number(parts).alias("at")).select(*data.columns, "query", each(groups, lambda i: i * parts + F.col("at")))
    met = shards.unionByName(blocks).repartitionById(groups * parts, F.col("task")).sortWithinPartitions("task", "query")
    found = met.mapInArrow(_search(k), "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
