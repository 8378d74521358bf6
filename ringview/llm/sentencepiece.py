"""SentencePiece encoding and decoding by batched Viterbi.

The vocabulary of a SentencePiece model (pieces, scores, byte pieces) is read from its file.  A text, its spaces
turned to U+2581 with one before it, falls into words at each U+2581 that follows another character (no piece spans
such a place).  Words that no cache holds are segmented in batches of equal length: at each end position all
substrings of all words are hashed at once, looked up in the sorted keys of the pieces, and the best predecessor is
kept as a back-pointer.  The segmentation has the largest sum of scores; characters outside the vocabulary become
byte pieces.  Decoding returns the text exactly.
"""

from __future__ import annotations

import re
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ringview.llm.common import keyed, lean, powers, prefix_hash, span_hash

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
#: Words kept in a worker's cache; words of one batch of the search (times their bytes); longest word searched in one go.
CACHE, CELLS = 1 << 17, 1 << 18
_WORD = re.compile("▁*[^▁]+|▁+")
_UNKNOWN_BELOW = 10.0


class Vocabulary:
    """Pieces of a model file, with sorted hash keys for lookups by array."""

    def __init__(self, blob: bytes):
        from sentencepiece import sentencepiece_model_pb2

        model = sentencepiece_model_pb2.ModelProto()
        model.ParseFromString(blob)
        if model.normalizer_spec.precompiled_charsmap or model.normalizer_spec.remove_extra_whitespaces:
            raise ValueError("only models that leave the text as it is can be decoded exactly")
        self.prefix = model.normalizer_spec.add_dummy_prefix
        kind = model.SentencePiece
        self.raw = [p.piece.encode() for p in model.pieces]
        plain = [i for i, p in enumerate(model.pieces) if p.type in (kind.NORMAL, kind.USER_DEFINED)]
        if any(re.search("[^▁]▁", model.pieces[i].piece) for i in plain):
            raise ValueError("a piece spans words")
        self.byte = np.full(256, -1, dtype=np.int32)
        for i, p in enumerate(model.pieces):
            if p.type == kind.BYTE:
                self.byte[int(p.piece[3:5], 16)] = i
                self.raw[i] = bytes([int(p.piece[3:5], 16)])
        if (self.byte < 0).any():
            raise ValueError("the model has no byte pieces")
        joined = np.frombuffer(b"".join(self.raw[i] for i in plain), dtype=np.uint8)
        end = np.cumsum([len(self.raw[i]) for i in plain])
        start = end - np.array([len(self.raw[i]) for i in plain])
        key = _key(prefix_hash(joined), start, end)
        order = np.argsort(key)
        if (np.diff(key[order]) == 0).any():
            raise ValueError("two pieces have one key")
        self.key, self.id = key[order], np.array(plain, dtype=np.int32)[order]
        score = np.array([model.pieces[i].score for i in plain], dtype=np.float32)
        self.score = score[order]
        self.unknown = np.float32(score.min() - _UNKNOWN_BELOW)
        self.longest = int((end - start).max())
        self.seen = np.zeros(1 << 20, dtype=bool)
        self.seen[self.key >> np.uint64(44)] = True
        self.bytes_all = np.frombuffer(b"".join(self.raw), dtype=np.uint8)
        self.size = np.array([len(x) for x in self.raw])
        self.begin = np.cumsum(self.size) - self.size
        self.lookup = set(self.raw[i] for i in plain)

    def probe(self, key: np.ndarray) -> np.ndarray:
        """Place of each key among the sorted keys, or -1; a bit table spares most substrings the search."""
        out = np.full(len(key), -1, dtype=np.int64)
        maybe = np.flatnonzero(self.seen[key >> np.uint64(44)])
        at = np.minimum(np.searchsorted(self.key, key[maybe]), len(self.key) - 1)
        hit = self.key[at] == key[maybe]
        out[maybe[hit]] = at[hit]
        return out

    def search(self, words: list[bytes], n: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words of ``n`` bytes each, one after another, and how many each has."""
        ids, sizes = [np.zeros(0, np.int32)], [np.zeros(0, np.int64)]
        step = max(1, CELLS // max(n, 1))
        for a in range(0, len(words), step):
            x, y = self._viterbi(words[a : a + step], n)
            ids.append(x)
            sizes.append(y)
        return np.concatenate(ids), np.concatenate(sizes)

    def _viterbi(self, words: list[bytes], n: int) -> tuple[np.ndarray, np.ndarray]:
        """Words advance together: at each end all starts are tried at once.  Only character starts are ever reached."""
        rows, every = len(words), np.arange(len(words))
        grid = np.frombuffer(b"".join(words), dtype=np.uint8).reshape(rows, n)
        first = np.ones((rows, n + 1), dtype=bool)
        first[:, :n] = (grid & 0xC0) != 0x80  # a character begins here
        up, down = powers(n + 1)
        prefix = np.zeros((rows, n + 1), dtype=np.uint64)
        np.cumsum((grid.astype(np.uint64) + np.uint64(1)) * up[:n], axis=1, out=prefix[:, 1:])
        best = np.full((rows, n + 1), -np.inf, dtype=np.float32)
        best[:, 0] = 0
        back = np.zeros((rows, n + 1), dtype=np.int32)
        piece = np.full((rows, n + 1), -1, dtype=np.int32)
        begun = np.zeros(rows, dtype=np.int64)  # where the character that ends here begins
        for e in range(1, n + 1):
            begun = np.where(first[:, e - 1], e - 1, begun)
            low = max(0, e - self.longest)
            width = e - low
            key = (prefix[:, e, None] - prefix[:, low:e]) * down[low:e] ^ (np.arange(width, 0, -1).astype(np.uint64) << np.uint64(56))
            at = self.probe(key.ravel())
            found = np.flatnonzero(at >= 0)
            total = np.full(rows * width, -np.inf, dtype=np.float32)
            total[found] = best[:, low:e].ravel()[found] + self.score[at[found]]
            at, total = at.reshape(rows, width), total.reshape(rows, width)
            pick = total.argmax(axis=1)
            top = total[every, pick]
            lone = first[:, e] & (at[every, begun - low] < 0)  # no piece is this one character
            other = np.where(lone, best[every, begun] + self.unknown, -np.inf).astype(np.float32)
            use = other > top
            best[:, e] = np.where(use, other, top)
            back[:, e] = np.where(use, begun, low + pick)
            piece[:, e] = np.where(use, -1, self.id[at[every, pick]])
        # all words are read off from their ends together
        end, live, step = np.full(rows, n), every, 0
        row, turn, got = [], [], []
        while len(live):
            e = end[live]
            b, ids = back[live, e], piece[live, e]
            known = ids >= 0
            row.append(live[known])
            turn.append(np.full(int(known.sum()), step))
            got.append(ids[known])
            step += 1
            for r, x, y in zip(live[~known].tolist(), b[~known].tolist(), e[~known].tolist(), strict=True):
                size = y - x
                row.append(np.full(size, r))
                turn.append(step + np.arange(size))
                got.append(self.byte[grid[r, x:y][::-1]])
            step += 4 * bool((~known).any())
            end[live] = b
            live = live[b > 0]
        row_, turn_, got_ = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (row, turn, got))
        order = np.lexsort((-turn_, row_))
        return got_[order].astype(np.int32), np.bincount(row_, minlength=rows)

    def decode(self, ids: np.ndarray, ends: np.ndarray) -> list[str]:
        """Texts of consecutive id lists, list k ending at ``ends[k]``."""
        size = self.size[ids]
        stop = np.cumsum(size)
        at = np.arange(int(stop[-1]) if len(stop) else 0) + np.repeat(self.begin[ids] - (stop - size), size)
        data = self.bytes_all[at].tobytes()
        edge = np.concatenate(([0], stop))[np.concatenate(([0], ends))].tolist()
        lead = len("▁".encode()) if self.prefix else 0
        return [data[a:b][lead:].decode(errors="replace").replace("▁", " ") for a, b in zip(edge[:-1], edge[1:], strict=True)]


def _key(prefix: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return span_hash(prefix, a, b) ^ ((b - a).astype(np.uint64) << np.uint64(56))


class Encoder:
    """Segments texts with a bounded cache of words."""

    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary
        self.reset()

    def reset(self) -> None:
        self.index: dict[str, int] = {}
        self.flat, self.start, self.size = np.zeros(1 << 20, np.int32), np.zeros(CACHE * 2, np.int64), np.zeros(CACHE * 2, np.int64)
        self.used = 0

    def _learn(self, words: list[str]) -> None:
        by_size: dict[int, list[tuple[str, bytes]]] = {}
        for w in words:
            raw = w.encode()
            by_size.setdefault(len(raw), []).append((w, raw))
        if len(self.index) + len(words) > len(self.start):
            self.start, self.size = (np.resize(x, 2 * len(x) + len(words)) for x in (self.start, self.size))
        for n, group in by_size.items():
            ids, size = self.v.search([raw for _, raw in group], n)
            if self.used + len(ids) > len(self.flat):
                self.flat = np.resize(self.flat, 2 * len(self.flat) + len(ids))
            k = len(self.index)
            self.start[k : k + len(group)] = self.used + np.cumsum(size) - size
            self.size[k : k + len(group)] = size
            self.flat[self.used : self.used + len(ids)] = ids
            self.used += len(ids)
            self.index.update(zip((w for w, _ in group), range(k, k + len(group)), strict=True))

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after another, and where each text's end."""
        if len(self.index) > CACHE:
            self.reset()
        lead = "▁" if self.v.prefix else ""
        lists = [_WORD.findall(lead + t.replace(" ", "▁")) if t else [] for t in texts]
        words = [w for x in lists for w in x]
        index = self.index
        if fresh := [w for w in dict.fromkeys(words) if w not in index]:
            self._learn(fresh)
        at = np.fromiter(map(index.__getitem__, words), dtype=np.int64, count=len(words))
        size = self.size[at]
        stop = np.cumsum(size)
        take = np.arange(int(stop[-1]) if len(stop) else 0) + np.repeat(self.start[at] - (stop - size), size)
        per_text = np.cumsum([len(x) for x in lists], dtype=np.int64)
        return self.flat[take], np.concatenate(([0], stop))[per_text] if len(lists) else np.zeros(0, np.int64)


@cache
def encoder(model: str, blob: bytes | None = None) -> Encoder:
    if blob is None:
        with open(model, "rb") as f:
            blob = f.read()
    return Encoder(Vocabulary(blob))


def _rows(model: str, check: bool):
    @lean
    def run(batches):
        e = encoder(model)
        for batch in batches:
            texts = [t or "" for t in batch.column("_t").to_pylist()]
            a = 0
            while a < len(texts):
                b, size = a, 0
                while b < len(texts) and (b == a or size + len(texts[b]) <= 1 << 20):
                    size += len(texts[b])
                    b += 1
                ids, ends = e.encode(texts[a:b])
                same = [x == y for x, y in zip(e.v.decode(ids, ends), texts[a:b], strict=True)] if check else [None] * (b - a)
                begin = np.concatenate(([0], ends))
                part = batch.slice(a, b - a)
                yield pa.RecordBatch.from_arrays(
                    [part.column("_d"), pa.array(np.diff(begin)), pa.ListArray.from_arrays(pa.array(begin.astype(np.int32)), pa.array(ids)), pa.array(same, pa.bool_())],
                    names=["_d", "n_tokens", "ids", "round_trip"],
                )
                a = b

    return run


def encode(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", model: str = MODEL, check: bool = True) -> DataFrame:
    """One row per document: doc_id, n_tokens, ids, round_trip (whether decoding gave the text again).

    Null and empty texts have no ids.  Texts are segmented whole; every worker reads the model file at ``model``.
    """
    return keyed(docs, id_col, text_col).select("_d", "_t").mapInArrow(_rows(model, check), "_d long, n_tokens long, ids array<int>, round_trip boolean").withColumnRenamed("_d", id_col)


def decode(tokens: DataFrame, ids_col: str = "ids", id_col: str = "doc_id", model: str = MODEL) -> DataFrame:
    """(doc_id, text) of id lists; null is empty."""

    def run(batches):
        v = encoder(model).v
        for batch in batches:
            lists = [np.array(x or [], dtype=np.int64) for x in batch.column("ids").to_pylist()]
            ends = np.cumsum([len(x) for x in lists], dtype=np.int64)
            texts = v.decode(np.concatenate([np.zeros(0, np.int64), *lists]), ends)
            yield pa.RecordBatch.from_arrays([batch.column("_d"), pa.array(texts, pa.string())], names=["_d", "text"])

    from pyspark.sql import functions as F

    return tokens.select(F.col(f"`{id_col}`").cast("long").alias("_d"), F.col(f"`{ids_col}`").alias("ids")).mapInArrow(run, "_d long, text string").withColumnRenamed("_d", id_col)
