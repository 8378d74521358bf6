"""Removal of long repeated byte strings, by threshold-bounded interval expansion on a Burrows-Wheeler transform.

Finding candidates.  Of each ``least``-byte string one 128-byte gram is its anchor, the one with the smallest hash, so
equal strings have equal anchors at equal places.  All starts of one anchor make a context: the text from the first
start to ``least`` bytes past the last.  Contexts whose anchor occurs once hold no repeat.  Equal contexts at two
places repeat throughout.  What is left, different contexts with one anchor, goes to a Burrows-Wheeler transform for
each batch of anchors: intervals are extended backwards breadth first, so common prefixes come by increasing
length, and expansion stops at ``least``; neighbours without a value by then share ``least`` bytes or more.

Crowded anchors (many different contexts) are split by place and by the bytes all starts of that place have in common,
first in steps of ``STEP`` starts, then, if that is not enough, start by start.
"""

from __future__ import annotations

import hashlib
import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.llm.common import keyed, lean, materialize, mix, prefix_hash, slices, span_hash, text_view

GRAM, LEAST = 128, 400
#: Contexts of an anchor that one transform may take; bytes of a transform; starts of a step; bytes of a piece of a long text.
CROWD, BLOCK, STEP, PIECE = 2048, 1 << 20, 32, 1 << 22
_MARK = 0xFF  # no byte of UTF-8
#: Bytes that the first sort of a transform compares; places whose ranks fit a key of 64 bits in threes.
FIRST, THREES = 8, 1 << 21


def _window_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of x[i:i+width] for each i where that is whole."""
    n = len(x)
    size = -(-n // width) * width
    padded = np.full(size, np.iinfo(np.uint64).max, dtype=np.uint64)
    padded[:n] = x
    grid = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    back = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - width + 1], ahead[width - 1 : n])


def contexts(data: np.ndarray, at: np.ndarray, least: int, gram: int) -> tuple[np.ndarray, ...]:
    """(text, first start, last start, anchor place, anchor hash) of each context; places count from ``data``'s start."""
    none = np.zeros(0, np.int64)
    if len(data) < least:
        return none, none, none, none, np.zeros(0, np.uint64)
    prefix = prefix_hash(data)
    i = np.arange(len(data) - gram + 1)
    h = mix(span_hash(prefix, i, i + gram))
    low = np.uint64((1 << 24) - 1)
    chosen = _window_min((h & ~low) | i.astype(np.uint64), least - gram + 1)
    size = np.diff(at)
    full = np.flatnonzero(size >= least)
    starts = np.concatenate([np.arange(at[k], at[k + 1] - least + 1) for k in full]) if len(full) else none
    text = np.repeat(full, size[full] - least + 1)
    if not len(starts):
        return none, none, none, none, np.zeros(0, np.uint64)
    anchor = (chosen[starts] & low).astype(np.int64)
    head = np.flatnonzero(np.concatenate(([True], (anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1]))))
    last = np.append(head[1:], len(starts)) - 1
    return text[head], starts[head], starts[last], anchor[head], h[anchor[head]]


def _digest(view: memoryview) -> bytes:
    return hashlib.blake2b(view, digest_size=16).digest()


def _pieces(data: np.ndarray, at: np.ndarray, least: int):
    """Long texts in pieces that overlap by less than ``least`` bytes, so that each start is in one piece: (bytes, offsets, shift)."""
    if len(at) > 2 or at[-1] <= PIECE:
        yield data, at, 0
        return
    for a in range(0, max(1, int(at[-1]) - least + 1), PIECE):
        part = data[a : a + PIECE + least - 1]
        yield part, np.array([0, len(part)]), a


def _context_rows(least: int, gram: int):
    @lean
    def run(batches):
        for batch in batches:
            for part, data, at in slices(batch, "_t"):
                for piece, ends, shift in _pieces(data, at, least):
                    text, first, last, anchor, h = contexts(piece, ends, least, gram)
                    if len(text):
                        view = memoryview(np.ascontiguousarray(piece))
                        digest = [_digest(view[a : b + least]) for a, b in zip(first.tolist(), last.tolist(), strict=True)]
                        base = ends[text] - shift
                        yield pa.RecordBatch.from_arrays(
                            [part.column("_d").take(pa.array(text)), part.column("_h").take(pa.array(text)), pa.array(h.view(np.int64)), pa.array(digest, pa.binary())]
                            + [pa.array((x - base).astype(np.int64)) for x in (first, last, anchor)],
                            names=["_d", "_h", "key", "dig", "s1", "s2", "a"],
                        )

    return run


def first_bytes(text: np.ndarray) -> np.ndarray:
    """The ``FIRST`` bytes from each place, round the end, as a number."""
    n = len(text)
    padded = np.resize(text, n + FIRST)
    return np.ndarray(n, dtype=">u8", buffer=padded, strides=(1,)).astype(np.uint64)


def sorted_starts(text: np.ndarray, depth: int) -> np.ndarray:
    """Places of ``text`` in the order of its rotations, compared for ``depth`` bytes at least.  A round compares three times
    the bytes of the one before (twice, if three ranks do not fit a key), at places that are not told apart yet only."""
    n = len(text)
    rank = np.empty(n, dtype=np.int64)  # where in the order the places with the same bytes begin
    have, times = FIRST, 3 if n <= THREES else 2
    key = first_bytes(text)
    order, at = np.argsort(key), np.arange(n)
    part, key = order, key[order]
    while True:
        head = np.concatenate(([True], key[1:] != key[:-1], [True]))
        begin = np.flatnonzero(head[:-1])
        rank[part] = np.repeat(at[begin], np.diff(np.append(begin, len(at))))
        at = at[~(head[:-1] & head[1:])]
        if have >= depth or not len(at):
            return order
        part = order[at]
        key = rank
        for k in range(1, times):
            key = key * n + np.roll(rank, -k * have)
        key = key[part]
        by_key = np.argsort(key)
        part, key = part[by_key], key[by_key]
        order[at] = part
        have *= times


def bounded_expansion(text: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, short): suffix order, and for each place r in it whether suffixes r-1 and r have under ``least`` bytes in
    common; computed from the Burrows-Wheeler transform, lengths in turn, up to ``least``.  Where that is over ``FIRST``,
    the intervals of the ``FIRST``-byte strings, which the sort compared as numbers, are the first to be extended.  An
    interval costs its runs of one character, not its places."""
    n = len(text)
    order = sorted_starts(text, least)
    bwt = text[order - 1]
    by_char = np.argsort(bwt, kind="stable")  # where a character's k-th occurrence is
    back = np.empty(n, dtype=np.int64)  # and what place its extension has
    back[by_char] = np.arange(n)
    keys = bwt[by_char].astype(np.int64) * (n + 1) + by_char
    alphabet = np.unique(bwt).astype(np.int64)
    short = np.zeros(n + 1, dtype=bool)
    short[[0, n]] = True
    lo, hi, length = np.array([0]), np.array([n]), 0
    if least > FIRST:
        first = first_bytes(text)[order]
        differ = first[1:] ^ first[:-1]
        edge = np.flatnonzero(differ) + 1
        short[edge] = True
        fresh = differ[edge - 1] < 256  # all but the last byte in common; the others were found at a shorter length
        lo, hi, length = np.concatenate(([0], edge[:-1]))[fresh], edge[fresh], FIRST
    head = np.flatnonzero(np.concatenate(([True], bwt[1:] != bwt[:-1])))  # runs of one character
    tail = np.append(head[1:], n)
    run = np.repeat(np.arange(len(head)), tail - head)
    for _ in range(length, least):
        if not len(lo):
            break
        begin, size = run[lo], run[hi - 1] - run[lo] + 1
        one = size == 1
        wide = size > 4 * len(alphabet)
        new_lo, new_hi = [back[lo[one]]], [back[hi[one] - 1] + 1]
        if wide.any():
            for c in alphabet:
                a = np.searchsorted(keys, c * (n + 1) + lo[wide])
                b = np.searchsorted(keys, c * (n + 1) + hi[wide])
                new_lo.append(a[a < b])
                new_hi.append(b[a < b])
        some = ~(one | wide)
        size = size[some]
        if len(size):
            of = np.repeat(np.arange(len(size)), size)
            at = np.arange(len(of)) + np.repeat(begin[some] - np.cumsum(size) + size, size)
            tag = of * 256 + bwt[head[at]]
            by_tag = np.argsort(tag, kind="stable")
            tag, at, of = tag[by_tag], at[by_tag], of[by_tag]
            change = np.flatnonzero(tag[1:] != tag[:-1])
            first, last = np.concatenate(([0], change + 1)), np.append(change, len(tag) - 1)
            new_lo.append(back[np.maximum(head[at[first]], lo[some][of[first]])])
            new_hi.append(back[np.minimum(tail[at[last]], hi[some][of[last]]) - 1] + 1)
        lo, hi = np.concatenate(new_lo), np.concatenate(new_hi)
        fresh = ~short[hi]
        lo, hi = lo[fresh], hi[fresh]
        short[hi] = True
    return order, short


def repeated(texts: list[bytes] | np.ndarray, ends: np.ndarray, least: int) -> np.ndarray:
    """For joined texts, each followed by a mark: whether the ``least`` bytes from a place occur at another place too
    (places with fewer bytes before the mark are of no account)."""
    order, short = bounded_expansion(texts, least)
    out = np.zeros(len(texts), dtype=bool)
    out[order] = ~(short[:-1] & short[1:])
    return out


def _runs(flag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    edge = np.diff(np.concatenate(([0], flag.astype(np.int8), [0])))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1) - 1


def _transform(least: int):
    """Contexts sorted by key: runs of starts, counted from the context's own, that repeat."""

    def work(keys, digs, ctx):
        size = np.array([len(x) for x in ctx])
        text = np.frombuffer(b"".join(x + b"\xff" for x in ctx), dtype=np.uint8)
        end = np.cumsum(size + 1)
        flag = repeated(text, end, least)
        valid = np.zeros(len(text), dtype=bool)
        for a, n in zip((end - size - 1).tolist(), size.tolist(), strict=True):
            valid[a : a + n - least + 1] = True
        x, y = _runs(flag & valid)
        row = np.searchsorted(end, x, "right")
        base = (end - size - 1)[row]
        pick = pa.array(row)
        return pa.RecordBatch.from_arrays([pa.array(keys).take(pick), pa.array(digs, pa.binary()).take(pick), pa.array((x - base).astype(np.int64)), pa.array((y - base).astype(np.int64))], names=["key", "dig", "x", "y"])

    @lean
    def run(batches):
        keys, digs, ctx, total = [], [], [], 0
        for batch in batches:
            for k, d, c in zip(batch.column("key").to_pylist(), batch.column("dig").to_pylist(), batch.column("ctx").to_pylist(), strict=True):
                if keys and k == keys[-1] and d == digs[-1]:
                    continue  # from a copy of a whole row
                if total >= BLOCK and k != keys[-1]:
                    yield work(keys, digs, ctx)
                    keys, digs, ctx, total = [], [], [], 0
                keys.append(k)
                digs.append(d)
                ctx.append(c)
                total += len(c) + 1
        if keys:
            yield work(keys, digs, ctx)

    return run


def _split(least: int, step: int):
    """Contexts to parts of ``step`` starts at fixed distances from the anchor, keyed by the bytes all those starts share."""

    @lean
    def run(batches):
        for batch in batches:
            out = []
            for k, d, c, back in zip(*(batch.column(n).to_pylist() for n in ("key", "dig", "ctx", "back")), strict=True):
                last = len(c) - least  # starts are 0 .. last; the anchor is at back
                for j in range((back - last) // step, back // step + 1):
                    low, high = back - step * (j + 1) + 1, back - step * j
                    a, b = max(low, 0), min(high, last)
                    if a <= b:
                        part = c[a : b + least]
                        core = hashlib.blake2b(struct.pack("<qq", k, j) + c[high : low + least], digest_size=8)
                        out.append((int.from_bytes(core.digest(), "little", signed=True), _digest(part), part, high - a, k, d, a))
            columns = list(zip(*out, strict=True)) if out else [[]] * 7
            types = [pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.binary(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(columns, types, strict=True)], names=["key", "dig", "ctx", "back", "pkey", "pdig", "shift"])

    return run


def _resolve(ctx: DataFrame, least: int, crowd: int, steps: tuple[int, ...]) -> DataFrame:
    """(key, dig, x, y): starts that also occur in another context of the key.  ``ctx``: key, dig, ctx, back."""
    parts = max(1, -(-int(ctx.agg(F.sum(F.length("ctx"))).first()[0] or 0) // BLOCK))
    spark_parts = int(ctx.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    few = ctx
    many = None
    if steps:
        crowded = materialize(ctx.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > crowd).select("key"), "crowded")
        if not crowded.isEmpty():
            few = ctx.join(crowded, "key", "left_anti")
            many = ctx.join(crowded, "key", "left_semi").dropDuplicates(["key", "dig"])
    found = few.select("key", "dig", "ctx").repartition(max(parts, min(spark_parts, 4 * parts)), "key").sortWithinPartitions("key", "dig").mapInArrow(_transform(least), "key long, dig binary, x long, y long")
    if many is None:
        return found
    part = materialize(many.mapInArrow(_split(least, steps[0]), "key long, dig binary, ctx binary, back long, pkey long, pdig binary, shift long"), "parts")
    each = part.groupBy("key", "dig").agg(F.count("*").alias("n"), F.min("ctx").alias("ctx"), F.min("back").alias("back"))
    each = materialize(each, "part-contexts")
    shared = each.groupBy("key").agg(F.count("*").alias("k")).where("k > 1").select("key")
    again = materialize(each.join(shared, "key", "left_semi").select("key", "dig", "ctx", "back"), "again")
    whole = each.where("n > 1").select("key", "dig", F.lit(0).cast("long").alias("x"), (F.length("ctx") - least).cast("long").alias("y"))
    marks = materialize(whole.unionByName(_resolve(again, least, crowd, steps[1:])), "part-marks")
    back = part.select("key", "dig", "pkey", "pdig", "shift").join(marks, ["key", "dig"])
    return found.unionByName(back.select(F.col("pkey").alias("key"), F.col("pdig").alias("dig"), (F.col("x") + F.col("shift")).alias("x"), (F.col("y") + F.col("shift")).alias("y")))


def _cut_contexts(least: int):
    @lean
    def run(batches):
        for batch in batches:
            data, at = text_view(batch.column("_t"))
            raw = memoryview(np.ascontiguousarray(data))
            out = []
            for base, want in zip(at.tolist(), batch.column("want").to_pylist(), strict=False):
                out += [(w["key"], w["dig"], bytes(raw[base + w["s1"] : base + w["s2"] + least]), w["a"] - w["s1"]) for w in want]
                if len(out) > 20_000:
                    yield _context_batch(out)
                    out = []
            yield _context_batch(out)

    return run


def _context_batch(out):
    columns = list(zip(*out, strict=True)) if out else [[]] * 4
    return pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(columns, (pa.int64(), pa.binary(), pa.binary(), pa.int64()), strict=True)], names=["key", "dig", "ctx", "back"])


def repeated_starts(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", least: int = LEAST, gram: int = GRAM, crowd: int = CROWD) -> DataFrame:
    """(_d, _h, starts array<struct<x, y>>): of each document with repeats, runs of places whose ``least`` bytes start elsewhere too."""
    rows = materialize(keyed(docs, id_col, text_col).mapInArrow(_context_rows(least, gram), "_d long, _h long, key long, dig binary, s1 long, s2 long, a long"), "contexts")
    keys = rows.groupBy("key").agg(F.count("*").alias("n"), (F.min("dig") != F.max("dig")).alias("various")).where("n > 1")
    shared = materialize(rows.join(materialize(keys, "anchors").select("key", "various"), "key"), "shared")
    alike = shared.where("not various").select("_d", "_h", F.col("s1").alias("x"), F.col("s2").alias("y"))
    other = shared.where("various")
    each = materialize(other.groupBy("key", "dig").agg(F.count("*").alias("n"), F.min(F.struct("_d", "_h", "s1", "s2", "a")).alias("r")), "distinct")
    want = each.select(F.col("r._d").alias("_d"), F.col("r._h").alias("_h"), F.struct("key", "dig", "r.s1", "r.s2", "r.a").alias("w")).groupBy("_d", "_h").agg(F.collect_list("w").alias("want"))
    texts = keyed(docs, id_col, text_col).alias("l").join(want.alias("r"), F.expr("l._d <=> r._d and l._h = r._h")).select("l._t", "r.want")
    ctx = materialize(texts.mapInArrow(_cut_contexts(least), "key long, dig binary, ctx binary, back long"), "context-bytes")
    span = F.col("r.s2") - F.col("r.s1")
    whole = each.where("n > 1").select("key", "dig", F.lit(0).cast("long").alias("x"), span.alias("y"))
    marks = _resolve(ctx, least, crowd, (STEP, 1))
    marks = materialize(whole.unionByName(marks), "marks")
    partly = other.join(marks, ["key", "dig"]).select("_d", "_h", (F.col("s1") + F.col("x")).alias("x"), (F.col("s1") + F.col("y")).alias("y"))
    return alike.unionByName(partly).groupBy("_d", "_h").agg(F.collect_list(F.struct("x", "y")).alias("starts"))


def covered(starts: list[dict], least: int) -> list[tuple[int, int]]:
    """Maximal runs [a, b) of bytes that the strings from these starts cover."""
    out: list[list[int]] = []
    for x, y in sorted((s["x"], s["y"]) for s in starts):
        if out and x <= out[-1][1]:
            out[-1][1] = max(out[-1][1], y + least)
        else:
            out.append([x, y + least])
    return [(a, b) for a, b in out]


def _cut(least: int):
    def run(batches):
        for batch in batches:
            texts = batch.column("_t").to_pylist()
            out = []
            for text, starts in zip(texts, batch.column("starts").to_pylist(), strict=True):
                raw = (text or "").encode()
                spans = covered(starts or [], least)
                kept, at, cut = [], 0, 0
                for a, b in spans:
                    kept.append(raw[at:a])
                    cut += b - a
                    at = b
                kept.append(raw[at:])
                out.append((len(raw), cut, [{"start": a, "stop": b} for a, b in spans], b"".join(kept)))
            n, cut, spans, kept = (list(x) for x in zip(*out, strict=True)) if out else ([], [], [], [])
            span_type = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))
            yield pa.RecordBatch.from_arrays(
                [batch.column("_d"), batch.column("_h"), pa.array(n, pa.int64()), pa.array(cut, pa.int64()), pa.array(spans, span_type), pa.array(kept, pa.binary())],
                names=["_d", "_h", "n_bytes", "n_removed", "spans", "kept"],
            )

    return run


def _cut_digest(least: int):
    inner = _cut(least)

    @lean
    def run(batches):
        for b in inner(batches):
            sha = pa.array([hashlib.sha256(x.as_buffer()).hexdigest() for x in b.column("kept")], pa.string())
            n = pa.array([len(x) for x in b.column("spans")], pa.int64())
            yield pa.RecordBatch.from_arrays([*b.columns[:4], n, sha], names=["_d", "_h", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return run


def remove_repeats(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", least: int = LEAST, gram: int | None = None, crowd: int = CROWD, digest_only: bool = False) -> DataFrame:
    """One row per document: _d, _h (its identity), n_bytes, n_removed, spans and kept bytes (or n_spans, kept_sha256).

    Each byte that a ``least``-byte string covers which also starts elsewhere, in this document or another, goes.
    Strings are judged on the input and may overlap; matches never cross documents.  Null is empty; texts under
    ``least`` bytes stay whole; repeated rows are copies of each other and lose everything that is long enough.
    """
    starts = materialize(repeated_starts(docs, text_col, id_col, least, gram or min(GRAM, max(1, least // 3)), crowd), "starts")
    joined = keyed(docs, id_col, text_col).alias("l").join(starts.alias("r"), F.expr("l._d <=> r._d and l._h = r._h"), "left").select("l._d", "l._h", "l._t", "r.starts")
    if digest_only:
        return joined.mapInArrow(_cut_digest(least), "_d long, _h long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
    return joined.mapInArrow(_cut(least), "_d long, _h long, n_bytes long, n_removed long, spans array<struct<start:long,stop:long>>, kept binary")
