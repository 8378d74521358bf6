"""Exact dedup by content-defined chunk recipes.

A rolling hash cuts each folded text (A-Z lower-cased) where the content says so, and every chunk gets an
identifier: its 64-bit hash, as long as all chunks of the table with that hash have one strong digest, else the
strong digest itself.  A text is then its recipe, the ordered list of its chunks' identifiers, about 1 % of its
size; only recipes are grouped and compared, and no text is moved between machines.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.llm.common import FOLD, keyed, lean, materialize, only_rows, slices

#: Bytes that the rolling hash sees; bits that must be zero at a cut (a chunk has 2**bits bytes on average); largest chunk.
WINDOW, CUT_BITS, MOST = 32, 11, 1 << 14
_GEAR = np.random.default_rng(7).integers(0, 1 << 32, 256, dtype=np.uint32)
_SCHEMA = "_d long, _h long, sha string, recipe array<long>, strong array<binary>"


def cuts(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Ends of all chunks (and the starts of texts); where a text is cut depends on its own bytes alone."""
    h = _GEAR[data]
    step = 1
    while step < WINDOW:
        h[step:] = h[step:] + (h[:-step] << np.uint32(step))
        step *= 2
    hit = np.flatnonzero(h >> np.uint32(32 - CUT_BITS) == 0) + 1
    text = np.searchsorted(at, hit - 1, "right") - 1
    hit = hit[hit - at[text] >= WINDOW] if len(hit) else hit
    ends = np.unique(np.concatenate((at, hit)))
    gap = np.diff(ends)
    for i in np.flatnonzero(gap > MOST):
        ends = np.append(ends, np.arange(ends[i] + MOST, ends[i + 1], MOST))
    return np.sort(ends)


@lean
def _recipes(batches):
    for batch in batches:
        for part, data, at in slices(batch, "_t"):
            folded = FOLD[data]
            ends = cuts(folded, at)
            view = memoryview(folded)
            pieces = [view[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            weak = np.array([xxhash.xxh64_intdigest(x) for x in pieces], dtype=np.uint64).view(np.int64)
            strong = pa.array([hashlib.sha256(x).digest()[:16] for x in pieces], pa.binary())
            sha = [hashlib.sha256(view[a:b]).hexdigest() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
            offsets = pa.array(np.searchsorted(ends[:-1], at).astype(np.int32))
            yield pa.RecordBatch.from_arrays(
                [part.column("_d"), part.column("_h"), pa.array(sha), pa.ListArray.from_arrays(offsets, pa.array(weak)), pa.ListArray.from_arrays(offsets, strong)],
                names=["_d", "_h", "sha", "recipe", "strong"],
            )


def chunk_dictionary(recipes: DataFrame) -> DataFrame:
    """(weak, copies, verified): each 64-bit chunk identifier, its uses, and whether one strong digest stands behind it."""
    chunk = recipes.select(F.explode(F.arrays_zip("recipe", "strong")).alias("c")).select(F.col("c.recipe").alias("weak"), F.col("c.strong").alias("strong"))
    return chunk.groupBy("weak").agg(F.count("*").alias("copies"), (F.min("strong") == F.max("strong")).alias("verified"))


def find_copies(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per document: _d, _h (its identity), keep_id, group_size, kept, text_sha256.

    Texts are equal if identical after lower-casing A-Z; null is empty, and empty texts are equal to each other.
    The largest id of a group stays (null ids are the smallest; among copies of the id the row with the larger
    hash, then any one), so each group keeps exactly one row.  An empty table gives no row; further columns of
    ``docs`` may have any name.
    """
    found = materialize(keyed(docs, id_col, text_col).mapInArrow(_recipes, _SCHEMA).withColumn("_n", F.monotonically_increasing_id()), "recipes")
    unsure = materialize(chunk_dictionary(found).where("not verified").select("weak"), "unsure")
    if unsure.isEmpty():
        named = found.withColumn("detail", F.lit(None).cast("array<binary>"))
    else:  # two contents share a 64-bit identifier: texts with it are told apart by their strong digests as well
        touched = found.select("_n", F.explode("recipe").alias("weak")).join(unsure, "weak", "left_semi").select("_n").distinct().withColumn("touched", F.lit(True))
        named = found.join(touched, "_n", "left").withColumn("detail", F.when(F.col("touched"), F.col("strong"))).drop("touched")
    named = named.withColumn("detail", F.coalesce("detail", F.array().cast("array<binary>"))).drop("strong")
    best = F.max(F.struct("_d", "_h", "_n"))
    groups = named.groupBy("recipe", "detail").agg(best.alias("best"), F.count("*").alias("n"), F.min("sha").alias("low"), F.max("sha").alias("high")).where("n > 1")
    wrong = F.raise_error(F.lit("equal recipes of different texts"))
    groups = materialize(groups.select("recipe", "detail", "best", F.when(F.col("low") == F.col("high"), F.col("n")).otherwise(wrong).alias("n")), "groups")
    joined = named.join(groups, ["recipe", "detail"], "left")
    return joined.select(
        "_d", "_h", F.when(F.col("n").isNull(), F.col("_d")).otherwise(F.col("best._d")).alias("keep_id"), F.coalesce("n", F.lit(1)).alias("group_size"),
        F.coalesce(F.col("best._n") == F.col("_n"), F.lit(True)).alias("kept"), F.col("sha").alias("text_sha256"),
    )


def deduplicate(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """The rows of ``docs`` that stay, with their own columns."""
    found = materialize(find_copies(docs, text_col, id_col), "copies")
    copies = found.groupBy("_d", "_h").agg(F.count("*").alias("_copies"), F.max("kept").alias("kept")).where("kept").drop("kept")
    return only_rows(docs, materialize(copies, "kept"), id_col, text_col)
