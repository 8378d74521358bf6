"""Quality classifier with supervised subword embeddings, trained by stochastic gradient descent in numpy.

Words, word pairs and character n-grams of a text are hashed to the rows of one table of vectors; a document is the
average of its rows, and a softmax over two classes reads it.  A trained model is linear in the average, so scoring
needs one number for each row, the difference of the two class outputs; that table goes to the executors (its size is
2**BITS numbers whatever the data).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringview.llm.common import FOLD, keyed, lean, materialize, mix, prefix_hash, slices, span_hash, word_runs

#: Rows of the vector table (a power of two), numbers of a vector, lengths of character n-grams in bytes.
BITS, WIDTH, GRAMS = 17, 12, (2, 3, 4, 5)
#: Words of a run that counts as new or repeated (rows 0 and 1 of the table); rows 2 and 3: another or the same word again.
RUN = 4
#: Training documents of each class at most (those with the smallest hash), passes, first learning rate.
SAMPLE, PASSES, RATE = 1500, 4, 0.5


def features(data: np.ndarray, at: np.ndarray, bits: int = BITS):
    """(row of text, row of table) of all features, one kind at a time; rows of text ascend within a kind."""
    text = FOLD[data]
    shift = np.uint64(64 - bits)
    prefix = prefix_hash(text)
    start, end, row = word_runs(text, at)
    if len(start):
        word = span_hash(prefix, start, end)
        yield row, (mix(word + np.uint64(1)) >> shift).astype(np.int64)
        if len(start) > 1:
            same = row[1:] == row[:-1]
            pair = word[:-1] * np.uint64(0x9FB21C651E98DF25) + word[1:]
            yield row[1:][same], (mix(pair[same]) >> shift).astype(np.int64)
            yield row[1:][same], 2 + (word[1:] == word[:-1])[same].astype(np.int64)
        if len(start) >= RUN:  # runs of words by whether the text has had them before, not by which they are
            run = row[RUN - 1 :] == row[: len(row) - RUN + 1]
            h, r = span_hash(prefix, start[: len(run)][run], end[RUN - 1 :][run]), row[: len(run)][run]
            order = np.lexsort((h, r))
            again = np.zeros(len(h), dtype=np.int64)
            again[order[1:]] = (h[order[1:]] == h[order[:-1]]) & (r[order[1:]] == r[order[:-1]])
            yield r, again
    owner = np.repeat(np.arange(len(at) - 1), np.diff(at))
    for n in GRAMS:
        m = len(text) - n + 1
        if m <= 0:
            continue
        gram = text[:m].astype(np.uint64)
        for k in range(1, n):
            gram = (gram << np.uint64(8)) | text[k : m + k]
        own = owner[:m] == owner[n - 1 :]
        gram = gram if own.all() else gram[own]
        gram = (gram + np.uint64(n << 56)) * np.uint64(0x9E3779B97F4A7C15)
        gram ^= gram >> np.uint64(29)
        gram *= np.uint64(0xD6E8FEB86659FD93)
        yield owner[:m][own], (gram >> shift).astype(np.int64)


def bags(data: np.ndarray, at: np.ndarray, bits: int = BITS) -> list[tuple[np.ndarray, np.ndarray]]:
    """(table rows, weights that sum to 1) of each text."""
    kinds = list(features(data, at, bits))
    out = []
    for r in range(len(at) - 1):
        own = np.concatenate([np.zeros(0, np.int64)] + [f[np.searchsorted(row, r) : np.searchsorted(row, r, "right")] for row, f in kinds])
        f, n = np.unique(own, return_counts=True)
        out.append((f, (n / max(1, n.sum())).astype(np.float32)))
    return out


def train(texts: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, bits: int = BITS, seed: int = 1) -> tuple[np.ndarray, float]:
    """One number for each table row, and one for all: their (weighted) sum is the log-odds of label 1."""
    rng = np.random.default_rng(seed)
    table = ((rng.random((1 << bits, WIDTH), dtype=np.float32) - 0.5) / WIDTH).astype(np.float32)
    out = np.zeros((2, WIDTH), dtype=np.float32)
    bias = np.zeros(2, dtype=np.float32)
    n, steps = len(labels), 0
    weight = np.array([n / max(1, 2 * (labels == c).sum()) for c in (0, 1)], dtype=np.float32)  # both classes count alike
    for _ in range(PASSES):
        for i in rng.permutation(n):
            rate = RATE * (1 - steps / (PASSES * n))
            steps += 1
            rows, w = texts[i]
            hidden = w @ table[rows] if len(rows) else np.zeros(WIDTH, np.float32)
            z = out @ hidden + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[labels[i]] -= 1
            p *= weight[labels[i]] * rate
            step = out.T @ p
            out -= np.outer(p, hidden)
            bias -= p * np.float32(0.1)
            if len(rows):
                table[rows] -= w[:, None] * (step * np.float32(min(len(rows), 200)))[None, :]
    line = out[1] - out[0]
    return table @ line, float(bias[1] - bias[0])


def _calibrate(logits: np.ndarray, labels: np.ndarray, weight: tuple[float, float] = (1.0, 1.0)) -> tuple[float, float]:
    """Slope and shift of a logistic curve through the training scores, by Newton steps.  ``weight``: how many labelled
    documents one of the sample stands for, by class, so that the curve has the shares of all of them."""
    c = np.asarray(weight, dtype=np.float64)[labels]
    c /= c.mean()
    x = np.stack([logits, np.ones_like(logits)], axis=1).astype(np.float64)
    mean, dev = x[:, 0].mean(), x[:, 0].std() + 1e-9
    x[:, 0] = (x[:, 0] - mean) / dev
    w = np.zeros(2)
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (c * p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(2)
        w += np.linalg.solve(h, x.T @ (c * (labels - p)) - 1e-2 * w)
    return float(w[0] / dev), float(w[1] - w[0] * mean / dev)


def _fit(bits: int, weight: tuple[float, float]):
    @lean
    def run(batches):
        texts, labels = [], []
        for batch in batches:
            a = 0
            y = batch.column("_y").to_pylist()
            for part, data, at in slices(batch, "_t", 1 << 20):
                texts += bags(data, at, bits)
                labels += y[a : a + part.num_rows]
                a += part.num_rows
        y = np.array(labels, dtype=np.int64)
        if len(set(labels)) < 2:  # nothing to tell apart: a constant score
            share = (y.sum() + 1) / (len(y) + 2)
            scores, bias = np.zeros(1 << bits, np.float32), float(np.log(share / (1 - share)))
        else:
            scores, bias = train(texts, y, bits)
            logits = np.array([w @ scores[f] + bias for f, w in texts])
            slope, shift = _calibrate(logits, y, weight)
            scores, bias = (scores * slope).astype(np.float32), bias * slope + shift
        yield pa.RecordBatch.from_arrays([pa.array([scores.astype("<f4").tobytes()], pa.binary()), pa.array([bias])], names=["scores", "bias"])

    return run


def held_out(id_: str) -> Column:
    """Rows that no model learns from: crc32 of the id as text leaves 2 modulo 4."""
    return F.coalesce(F.crc32(F.col(id_).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def few_smallest(hash_: str, n, sample: int) -> Column:
    """Rows of which the ``sample`` smallest hashes of ``n`` are among, four times as many on average: what is to be sorted
    does not grow with the table.  (That fewer than ``sample`` of them are left has a chance below 1e-100 for the samples
    used here.)"""
    share = F.greatest(F.lit(4.0) * sample, F.lit(1000.0)) / n
    return (F.col(hash_).cast("double") + 2.0**63) / 2.0**64 < share


def fit(docs: DataFrame, labels: DataFrame, text_col: str = "text", id_col: str = "doc_id", label_col: str = "quality", bits: int = BITS, sample: int = SAMPLE) -> tuple[np.ndarray, float]:
    """Learn from labelled documents outside the held-out part, ``sample`` of each class at most (smallest hash first).
    The scores have the shares of both classes among all these documents, whatever the sample has."""
    y = labels.select(F.col(f"`{id_col}`").cast("long").alias("_d"), F.col(f"`{label_col}`").cast("int").alias("_y")).where("_y in (0, 1) and _d is not null")
    y = y.groupBy("_d").agg(F.max("_y").alias("_y")).where(~held_out("_d")).withColumn("_r", F.xxhash64("_d"))
    n = dict(y.groupBy("_y").count().collect())
    weight = tuple(max(1.0, n.get(c, 0) / max(1, sample)) for c in (0, 1))
    first = lambda c: y.where(F.col("_y") == c).where(few_smallest("_r", F.lit(max(1, n.get(c, 0))), sample)).orderBy("_r", "_d").limit(sample)
    y = materialize(first(0).unionByName(first(1)), "labelled")
    d = docs.select(F.col(f"`{id_col}`").cast("long").alias("_d"), F.col(f"`{text_col}`").alias("_t"))
    rows = d.join(F.broadcast(y), "_d").select("_t", "_y", "_r", "_d")  # 2*sample rows of numbers
    model = rows.repartition(1).sortWithinPartitions("_r", "_d", "_t").select("_t", "_y").mapInArrow(_fit(bits, weight), "scores binary, bias double").first()
    if model is None:  # no labelled row: a constant score
        return np.zeros(1 << bits, np.float32), 0.0
    return np.frombuffer(model["scores"], dtype="<f4").copy(), model["bias"]


def logits(scores: np.ndarray, bias: float, data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Log-odds of label 1 of each text."""
    bits = int(len(scores)).bit_length() - 1
    n = len(at) - 1
    total, count = np.zeros(n), np.zeros(n)
    for row, f in features(data, at, bits):
        total += np.bincount(row, weights=scores[f], minlength=n)
        count += np.bincount(row, minlength=n)
    return total / np.maximum(count, 1) + bias


def _score(scores: np.ndarray, bias: float):
    @lean
    def run(batches):
        for batch in batches:
            for part, data, at in slices(batch, "_t", 1 << 19):
                p = 1 / (1 + np.exp(-np.clip(logits(scores, bias, data, at), -40, 40)))
                yield pa.RecordBatch.from_arrays([part.column("_d"), part.column("_h"), pa.array(p)], names=["_d", "_h", "score"])

    return run


def score(docs: DataFrame, model: tuple[np.ndarray, float], text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per document: _d, _h (its identity), score in [0, 1].  Null and empty texts get the model's constant."""
    return keyed(docs, id_col, text_col).mapInArrow(_score(*model), "_d long, _h long, score double")


def keep_good(docs: DataFrame, model: tuple[np.ndarray, float], text_col: str = "text", id_col: str = "doc_id", least: float = 0.7) -> DataFrame:
    """The rows of ``docs`` with a score of ``least`` or more; the text passes through once, with all columns beside it."""
    plain = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_all"), F.col(f"`{text_col}`").cast("string").alias("_t"))
    scores, bias = model

    @lean
    def run(batches):
        for batch in batches:
            keep = []
            for _, data, at in slices(batch, "_t", 1 << 19):
                keep.append(1 / (1 + np.exp(-np.clip(logits(scores, bias, data, at), -40, 40))) >= least)
            kept = batch.filter(pa.array(np.concatenate(keep))) if keep else batch
            yield kept.select(["_all"])

    schema = plain.select("_all").schema
    return plain.mapInArrow(run, schema).select("_all.*")
