"""Language identification by error-correcting output codes.

Each language has a codeword; for each of its bits a binary classifier over hashed byte n-grams is trained.  Decoding
weighs the loss of every bit of every codeword at the classifiers' margins and takes the codeword with the least; if
the runner-up is close the document is flagged as ambiguous.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ringview.llm.common import FOLD, keyed, lean, materialize, slices
from ringview.llm.quality import few_smallest, held_out

#: log2 of the number of hashed n-grams, their lengths in bytes.
BITS, GRAMS = 12, (1, 2, 3, 4)
#: Training documents of each language at most (smallest hash first), and of all languages together (but for LEAST of
#: each), passes, learning rate.
SAMPLE, TOTAL, LEAST, PASSES, RATE = 300, 12_000, 8, 60, 0.5
#: Score under which the choice counts as ambiguous.
CLEAR = 0.75


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def codewords(k: int, seed: int = 3) -> np.ndarray:
    """k rows of +1 and -1: the exhaustive code for up to 5 languages, else random columns, of many the code with
    the largest smallest distance."""
    if k < 2:
        return np.ones((k, 1), dtype=np.float32)
    if k <= 5:
        return np.array([(1, *x) for x in itertools.product((1, -1), repeat=k - 1) if -1 in x], dtype=np.float32).T
    rng = np.random.default_rng(seed)
    best, far = None, -1
    for _ in range(50):
        code = rng.choice((1, -1), size=(k, int(np.ceil(10 * np.log2(k))))).astype(np.float32)
        code = code[:, np.abs(code.sum(axis=0)) < k]
        distance = (code.shape[1] - code @ code.T) / 2
        np.fill_diagonal(distance, code.shape[1])
        if distance.min() > far:
            best, far = code, distance.min()
    return best


def profiles(data: np.ndarray, at: np.ndarray, bits: int = BITS) -> np.ndarray:
    """A unit vector of damped n-gram counts for each text (zero for an empty one)."""
    text = FOLD[data]
    rows = len(at) - 1
    counts = np.zeros(rows << bits)
    owner = np.repeat(np.arange(rows), np.diff(at))
    for n in GRAMS:
        m = len(text) - n + 1
        if m <= 0:
            continue
        gram = text[:m].astype(np.uint32)
        for k in range(1, n):
            gram = (gram << np.uint32(8)) | text[k : m + k]
        cell = ((gram + np.uint32(n)) * np.uint32(0x9E3779B1)) >> np.uint32(32 - bits)
        cell = (owner[:m] << bits) + cell
        own = owner[:m] == owner[n - 1 :]
        counts += np.bincount(cell[own], minlength=rows << bits)
    x = np.sqrt(counts.reshape(rows, -1)).astype(np.float32)
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)


def train(x: np.ndarray, targets: np.ndarray, weight: np.ndarray, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Logistic classifiers, one for each column of ``targets`` (+1 or -1), by stochastic gradient descent."""
    rng = np.random.default_rng(seed)
    w, b = np.zeros((x.shape[1], targets.shape[1]), dtype=np.float32), np.zeros(targets.shape[1], dtype=np.float32)
    for epoch in range(PASSES):
        rate = np.float32(20 * RATE * (1 - epoch / PASSES))
        for at in np.array_split(rng.permutation(len(x)), max(1, len(x) // 64)):
            y = targets[at]
            g = -y / (1 + np.exp(np.clip(y * (x[at] @ w + b), -30, 30))) * weight[at, None] / len(at)
            w -= rate * (x[at].T @ g) + rate * np.float32(1e-5) * w
            b -= np.float32(0.1) * rate * g.sum(axis=0)
    return w, b


def _fit(bits: int):
    @lean
    def run(batches):
        x, y = [np.zeros((0, 1 << bits), np.float32)], []
        for batch in batches:
            y += batch.column("_y").to_pylist()
            for _, data, at in slices(batch, "_t", 1 << 18):
                x += [profiles(data[at[i] : at[min(i + 32, len(at) - 1)]], at[i : i + 33] - at[i], bits) for i in range(0, len(at) - 1, 32)]
        names = sorted(set(y))
        code = codewords(len(names))
        place = {n: i for i, n in enumerate(names)}
        index = np.array([place[v] for v in y], dtype=np.int64)
        share = len(y) / (max(1, len(names)) * np.maximum(1, np.bincount(index, minlength=len(names)))).astype(np.float32)
        if len(names) > 1:
            w, b = train(np.concatenate(x), code[index], share[index])
        else:
            w, b = np.zeros((1 << bits, 1), np.float32), np.ones(1, np.float32)
        yield pa.RecordBatch.from_arrays([pa.array([names], pa.list_(pa.string())), pa.array([w.astype("<f4").tobytes()], pa.binary()), pa.array([b.astype("<f4").tobytes()], pa.binary())], names=["names", "w", "b"])

    return run


def fit(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", lang_col: str = "lang", bits: int = BITS, sample: int = SAMPLE) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Learn from documents outside the held-out part, ``sample`` of each language at most (smallest hash first), fewer of
    each if there are so many languages that TOTAL would be passed.  Any number of languages gets codewords."""
    light = docs.select(F.col(f"`{id_col}`").cast("long").alias("_d"), F.col(f"`{lang_col}`").cast("string").alias("_y"))
    light = light.where("_y is not null and _d is not null").where(~held_out("_d")).withColumn("_r", F.xxhash64("_d"))
    per = materialize(light.groupBy("_y").agg(F.count("*").alias("_n")), "languages")
    light = light.join(per, "_y").where(few_smallest("_r", F.col("_n"), sample)).drop("_n")
    first = light.withColumn("_k", F.row_number().over(Window.partitionBy("_y").orderBy("_r", "_d"))).where(F.col("_k") <= sample)
    few = materialize(first.select("_d", "_y", "_r", "_k"), "sample")
    few = few.where(F.col("_k") <= max(LEAST, TOTAL // max(1, few.select("_y").distinct().count()))).drop("_k")
    d = docs.select(F.col(f"`{id_col}`").cast("long").alias("_d"), F.col(f"`{text_col}`").alias("_t"), F.col(f"`{lang_col}`").cast("string").alias("_y"))
    rows = d.join(F.broadcast(few), ["_d", "_y"])  # TOTAL rows of numbers, or LEAST of each language
    model = rows.repartition(1).sortWithinPartitions("_r", "_d", "_t").select("_t", "_y").mapInArrow(_fit(bits), "names array<string>, w binary, b binary").first()
    if model is None:
        return [], np.zeros((1 << bits, 1), np.float32), np.ones(1, np.float32)
    b = np.frombuffer(model["b"], dtype="<f4").copy()
    return list(model["names"]), np.frombuffer(model["w"], dtype="<f4").reshape(-1, len(b)).copy(), b


def decode(margin: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(codeword, score): the codeword with the least loss, and its share when losses are weighed against each other."""
    loss = np.logaddexp(0, -margin[:, None, :] * code[None, :, :]).sum(axis=2)
    p = np.exp(-(loss - loss.min(axis=1, keepdims=True)))
    p /= p.sum(axis=1, keepdims=True)
    best = loss.argmin(axis=1) if code.shape[0] else np.zeros(len(margin), np.int64)
    return best, p[np.arange(len(p)), best]


def _predict(names: list[str], w: np.ndarray, b: np.ndarray):
    bits, code = int(len(w)).bit_length() - 1, codewords(len(names))

    @lean
    def run(batches):
        for batch in batches:
            for part, data, at in slices(batch, "_t", 1 << 18):
                texts = part.column("_t").to_pylist()
                lang, score = [], []
                for i in range(0, len(texts), 32):
                    ends = at[i : i + 33]
                    if names:
                        best, p = decode(profiles(data[ends[0] : ends[-1]], ends - ends[0], bits) @ w + b, code)
                        lang += [names[k] for k in best]
                        score += p.tolist()
                    else:
                        lang += ["und"] * (len(ends) - 1)
                        score += [0.0] * (len(ends) - 1)
                for i, t in enumerate(texts):
                    if not t or not has_letter(t):
                        lang[i], score[i] = "und", 0.0
                yield pa.RecordBatch.from_arrays([part.column("_d"), part.column("_h"), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array([s < CLEAR for s in score], pa.bool_())], names=["_d", "_h", "lang_pred", "score", "ambiguous"])

    return run


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray, np.ndarray], text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per document: _d, _h (its identity), lang_pred, score in [0, 1], ambiguous.

    Null texts and texts without a letter are ``und`` with score 0, as is everything when no document had a language.
    """
    return keyed(docs, id_col, text_col).mapInArrow(_predict(*model), "_d long, _h long, lang_pred string, score double, ambiguous boolean")
