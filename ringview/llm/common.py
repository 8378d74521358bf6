"""Helpers shared by the pipeline operators: shared-folder tables, row identity, Arrow text views, word runs."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import functools
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Byte table that lower-cases A-Z only.
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
#: Byte table: 1 for the white space that separates words (space, and 0x09 to 0x0D).
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True

_own_folder: list[str] = []
_tables: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a temporary one only where that is unset and all runs on one machine (tests)."""
    path = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own_folder:
        _own_folder.append(tempfile.mkdtemp(prefix="ringview-"))
        atexit.register(shutil.rmtree, _own_folder[0], True)
    return _own_folder[0]


def table_path(spark: SparkSession, tag: str) -> str:
    _tables.append(f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}")
    return _tables[-1]


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again: cuts lineage, survives lost executors."""
    path = table_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextlib.contextmanager
def only_result(spark: SparkSession):
    """Tables written inside are deleted at the end; what is to stay is written last, under a path from ``keep``."""
    before = len(_tables)
    kept: list[str] = []

    def keep(df: DataFrame, tag: str) -> DataFrame:
        out = materialize(df, tag)
        kept.append(_tables[-1])
        return out

    try:
        yield keep
    finally:
        path = spark._jvm.org.apache.hadoop.fs.Path
        for t in [t for t in _tables[before:] if t not in kept]:
            p = path(t)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
            _tables.remove(t)


def row_hash(*columns: Column) -> Column:
    """Tells rows of one id apart by the columns that an operator reads; rows with equal id and hash are copies of each
    other to it."""
    return F.xxhash64(*[c.cast("string") for c in columns])


def keyed(df: DataFrame, id_col: str, text_col: str, *more: Column) -> DataFrame:
    """(_d, _h, _t): id (null kept), hash of the text, and text, whatever other columns are called; no others are read."""
    text = F.col(f"`{text_col}`").cast("string")
    return df.select(F.col(f"`{id_col}`").cast("long").alias("_d"), row_hash(text).alias("_h"), text.alias("_t"), *more)


def only_rows(df: DataFrame, keys: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows of ``df`` whose (_d, _h) is in ``keys`` (a row for each kept row, with ``_copies``: how many rows had that id
    and text).  Of copies one stays, any of them."""
    whole = F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("_all")
    named = df.select(whole, F.col(f"`{id_col}`").cast("long").alias("_d"), row_hash(F.col(f"`{text_col}`")).alias("_h")).alias("d")
    on = F.expr("d._d <=> k._d and d._h = k._h")
    single = named.join(keys.where("_copies = 1").alias("k"), on, "left_semi")
    repeated = named.join(keys.where("_copies > 1").alias("k"), on, "left_semi").dropDuplicates(["_d", "_h"])
    return single.unionByName(repeated).select("_all.*")


def text_view(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts one after another, and n+1 offsets.  A null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64) if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and len(data) else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def slices(batch: pa.RecordBatch, text: str, limit: int = 2 << 20) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Parts of a batch with about ``limit`` bytes of text (one row at least): memory stays bounded, work stays in cache."""
    data, at = text_view(batch.column(text))
    first = 0
    while first < batch.num_rows:
        last = max(first + 1, int(np.searchsorted(at, at[first] + limit, "right")) - 1)
        last = min(last, batch.num_rows)
        yield batch.slice(first, last - first), data[at[first] : at[last]], at[first : last + 1] - at[first]
        first = last


def lean(run):
    """A mapInArrow function after which the worker, which lives on, gives its free memory back."""

    @functools.wraps(run)
    def f(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):
                ctypes.CDLL(None).malloc_trim(0)

    return f


def word_runs(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and row of each word, a run of bytes that are not SPACE; a word ends with its text."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, none
    word = ~SPACE[data]
    edge = np.zeros(len(data) + 1, dtype=bool)
    edge[at] = True
    head = word & (edge[:-1] | np.concatenate(([True], ~word[:-1])))
    tail = word & (edge[1:] | np.concatenate((~word[1:], [True])))
    start, end = np.flatnonzero(head), np.flatnonzero(tail) + 1
    return start, end, np.searchsorted(at, start, "right") - 1


def mix(h: np.ndarray) -> np.ndarray:
    """Finalise 64-bit hashes (in place)."""
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(32)
    return h


BASE = 0x9E3779B97F4A7C55
_powers: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and BASE**-i modulo 2**64 for i < n."""
    if len(_powers.get("up", ())) < n:
        size = 1 << max(16, int(n - 1).bit_length())
        for name, base in (("up", BASE), ("down", pow(BASE, -1, 1 << 64))):
            p = np.full(size, base, dtype=np.uint64)
            p[0] = 1
            _powers[name] = np.multiply.accumulate(p)
    return _powers["up"][:n], _powers["down"][:n]


def prefix_hash(data: np.ndarray) -> np.ndarray:
    """P with span_hash(P, a, b) the same for equal byte strings."""
    up, _ = powers(len(data) + 1)
    out = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    _, down = powers(len(prefix))
    return (prefix[b] - prefix[a]) * down[a]


def bit_counts(hashes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Rows of 64 counts: how many hashes of each run (runs begin at ``first``, none empty) have each bit."""
    size = np.diff(np.append(first, len(hashes)))
    parts = -(-size // 255)
    block_row = np.repeat(np.arange(len(first)), parts)
    begin = np.cumsum(parts) - parts
    block = np.repeat(first, parts) + 255 * (np.arange(len(block_row)) - begin[block_row])
    out = np.zeros((len(first), 8, 8), dtype=np.int64)
    ones = np.uint64(0x0101010101010101)
    for k in range(8):
        lanes = np.add.reduceat((hashes >> np.uint64(k)) & ones, block)
        out[:, :, k] = np.add.reduceat(lanes.astype("<u8").view(np.uint8).reshape(-1, 8).astype(np.int64), begin, axis=0)
    return out.reshape(-1, 64)


def components(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each node that is in an edge, and the smallest node of its component."""
    nodes, at = np.unique(np.concatenate((u, v)), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while len(a):
        lo, hi = np.minimum(root[a], root[b]), np.maximum(root[a], root[b])
        open_ = lo != hi
        if not open_.any():
            break
        a, b = lo[open_], hi[open_]
        np.minimum.at(root, b, a)
        while not np.array_equal(root, up := root[root]):
            root = up
    return nodes, nodes[root]
