"""Products of matrix chains, maintained under low-rank updates."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.functions.rings import IntRing, NumberRing
from ringview.operators.engine import Engine
from ringview.operators.factored import TERM, FactoredDelta, Term, apply_factored, rank_one
from ringview.operators.relation import COUNT, KeyedRelation, join, marginalize
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder, chain_order
from ringview.sources.io import written


def chain_query(n: int, ring: NumberRing | None = None) -> NaturalJoinQuery:
    """A1[x1,x2] ... An[xn,xn+1] with the inner indices summed."""
    return NaturalJoinQuery({f"A{i}": (f"x{i}", f"x{i + 1}") for i in range(1, n + 1)}, ("x1", f"x{n + 1}"), ring or IntRing())


def order_of(shape: tuple | int, n: int) -> VariableOrder:
    """A parenthesization (nested pairs of indices from 0) as an order of the inner indices below both ends."""
    parent: dict[str, str | None] = {"x1": None, f"x{n + 1}": "x1"}

    def span(s: tuple | int) -> tuple[int, int]:
        return (s, s + 1) if isinstance(s, int) else (span(s[0])[0], span(s[1])[1])

    def place(s: tuple | int, above: str) -> None:
        if isinstance(s, tuple):
            cut = f"x{span(s[0])[1] + 1}"
            parent[cut] = above
            place(s[0], cut)
            place(s[1], cut)

    place(shape, f"x{n + 1}")
    return VariableOrder(parent)


#: Numbers of a strip of rows or columns that a task multiplies at once, its rows at most, and the longest inner side that strips
#: take whole: beyond it cells are multiplied one by one and summed by Spark.
STRIP, STRIP_ROWS, INNER = 1 << 16, 1024, 1 << 14
#: Cells that a task gathers before it hands them on as pieces of strips.
GATHERED = 1 << 19
#: Products that wait at the root before their factors are written as one.
WAITING = 8


def _piece(at: np.ndarray, place: np.ndarray, v: np.ndarray) -> bytes:
    """Cells of a block of rows, column by column, whole numbers in as few bytes as the largest of them needs."""
    if v.dtype.kind == "f" and (v == np.rint(v)).all() and np.abs(v).max() < 1 << 53:
        v = v.astype("i8")
    kind = "f8" if v.dtype.kind == "f" else next(k for k in ("i2", "i4", "i8") if np.iinfo(k).min <= v.min() and v.max() <= np.iinfo(k).max)
    return b"".join((kind.encode(), at.astype("<u2").tobytes(), place.astype("<u2").tobytes(), v.astype(f"<{kind}").tobytes()))


def _whole(pieces: Sequence[bytes], rows: int, inner: int, kind: str) -> np.ndarray:
    """The block of rows, dense, of all its pieces; cells that are there twice are summed."""
    m = np.zeros((rows, inner), kind)
    for p in pieces:
        width = int(p[1:2])
        n = (len(p) - 2) // (4 + width)
        at, place = np.frombuffer(p, "<u2", 2 * n, 2).reshape(2, n)
        np.add.at(m, (at, place), np.frombuffer(p, f"<{p[:2].decode()}", n, 2 + 4 * n).astype(kind))
    return m


def _gathered(cells: DataFrame, keys: Sequence[str]) -> DataFrame:
    """(keys, piece) of cells (keys, at, place, v): a task's cells of a block travel together, without their keys."""

    def pieces(held: list[pd.DataFrame]) -> pd.DataFrame:
        cols = {c: np.concatenate([p[c].to_numpy() for p in held]) for c in (*keys, "at", "place", "v")}
        by = np.lexsort([cols[c] for c in ("place", "at", *reversed(keys))])
        cols = {c: x[by] for c, x in cols.items()}
        cuts = np.flatnonzero(np.any([np.diff(cols[k], prepend=cols[k][0] - 1) for k in keys], axis=0))
        ends = [*cuts[1:], len(by)]
        return pd.DataFrame({k: cols[k][cuts] for k in keys} | {"piece": [_piece(*(cols[c][x:y] for c in ("at", "place", "v"))) for x, y in zip(cuts, ends, strict=True)]})

    def gather(batches):
        held, n = [], 0
        for p in batches:
            held, n = [*held, p], n + len(p)
            if n >= GATHERED:
                yield pieces(held)
                held, n = [], 0
        if n:
            yield pieces(held)

    return cells.mapInPandas(gather, ", ".join(f"{k} long" for k in keys) + ", piece binary")


def _met(df: DataFrame, by: str, value: str, most: int = 1 << 31) -> DataFrame:
    """``value`` listed by ``by``, of ``most`` values at most, in one shuffle, and in so few partitions that the pairs of two
    sides are not too many tasks."""
    tasks = min(most, max(32, 4 * df.sparkSession.sparkContext.defaultParallelism))
    return df.repartition(tasks, by).groupBy(by).agg(F.collect_list(value).alias(value)).coalesce(tasks)


def _strips(cells: DataFrame, side: str, rows: int, dense: DataFrame) -> DataFrame:
    """(b, piece): ``rows`` rows of ``side``, with all of the inner side, as a list of pieces."""
    at = F.pmod(F.col(side).cast("long"), F.lit(rows))
    placed = cells.where("v is not null").join(F.broadcast(dense), "k").select(F.expr(f"({side} - pmod({side}, {rows})) div {rows}").cast("long").alias("b"), at.cast("int").alias("at"), "place", "v")
    return _met(_gathered(placed, ["b"]), "b", "piece")


def exact_product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a times b transposed; whole numbers stay exact, and leave 64 bits with an error only."""
    if a.dtype.kind == "f":
        return a @ b.T
    most = int(max(abs(int(a.max())), abs(int(a.min())))) * int(max(abs(int(b.max())), abs(int(b.min())))) * a.shape[1]
    if most < 1 << 53:
        return np.rint(a.astype(float) @ b.astype(float).T).astype(np.int64)
    if most < 1 << 63:
        return a @ b.T
    out = a.astype(object) @ b.astype(object).T
    if max(out.max(), -out.min() - 1) >= 1 << 63:
        raise OverflowError("a cell of the product leaves 64 bits")
    return out.astype(np.int64)


def multiplied(left: DataFrame, right: DataFrame, kind: str, by_left: bool = False) -> DataFrame | None:
    """Cells (i, j, v), those of zero left out, of the product of ``left`` (i, k, v) and ``right`` (k, j, v).  Each cell is
    made whole in one task, so no cell is ever shuffled.  None if the inner side is longer than INNER.  The inner side is read
    from ``right``, or with ``by_left`` from ``left``."""
    spark = left.sparkSession
    inner = sorted(r[0] for r in (left if by_left else right).where("k is not null").select("k").distinct().limit(INNER + 1).collect())
    if len(inner) > INNER:
        return None
    n, numpy_kind = max(1, len(inner)), "<f8" if kind == "double" else "<i8"
    dense = spark.createDataFrame([(k, i) for i, k in enumerate(inner)], f"k {dict(right.dtypes)['k']}, place int")
    rows = max(1, min(STRIP_ROWS, STRIP // n))
    a, b = _strips(left, "i", rows, dense), _strips(right, "j", rows, dense).toDF("c", "other")

    def cells(batches):
        for p in batches:
            for x, y, left_, right_ in zip(p["b"], p["c"], p["piece"], p["other"], strict=True):
                m = exact_product(_whole(left_, rows, n, numpy_kind), _whole(right_, rows, n, numpy_kind))
                for start in range(0, rows, 64):
                    i, j = np.nonzero(m[start : start + 64])
                    if len(i):
                        yield pd.DataFrame({"i": i + start + x * rows, "j": j + y * rows, "v": m[start : start + 64][i, j]})

    return a.crossJoin(b).mapInPandas(cells, f"i long, j long, v {kind}")


class MatrixChain:
    """Coordinate matrices (row, column, v) as DataFrames; views of partial products are kept.

    The product itself, which can have the square of a matrix's rows, is kept as a sum of products of two tables: those of
    the start, and a pair for each change.  ``product`` multiplies them out, all of them in one pass."""

    def __init__(self, mats: Sequence[DataFrame], dims: Sequence[int], balanced: bool = True, ring: NumberRing | None = None, updatable: Sequence[int] | None = None):
        self.n = len(mats)
        self.q = chain_query(self.n, ring)
        self.order = order_of(chain_order(dims, balanced), self.n)
        self.engine = Engine(self.q, self.order, None if updatable is None else [f"A{i + 1}" for i in updatable])
        self.kind = (ring or IntRing()).type_name
        self.mats = [m.select(F.col(m.columns[0]).alias(f"x{i + 1}"), F.col(m.columns[1]).alias(f"x{i + 2}"), F.col(m.columns[2]).cast(self.kind).alias("v")) for i, m in enumerate(mats)]
        #: A matrix of few cells goes to the others' tasks, else Spark, which sees its table only, shuffles a large one by the inner index.
        self.mats = [F.broadcast(m) if dims[i] * dims[i + 1] <= INNER else m for i, m in enumerate(self.mats)]
        self.root = self.engine.tree.roots[0]
        #: Pairs of relations of one end each that share their inner index.
        self.terms: list[tuple[KeyedRelation, KeyedRelation]] = []
        self._load()

    @property
    def ends(self) -> tuple[str, str]:
        return "x1", f"x{self.n + 1}"

    def _load(self) -> None:
        from ringview.operators.engine import view
        from ringview.plans.viewtree import Leaf, Node

        seen = {f"A{i + 1}": KeyedRelation(m.withColumn(COUNT, F.lit(1).cast("long")), (f"x{i + 1}", f"x{i + 2}"), self.q.ring) for i, m in enumerate(self.mats)}

        def at(node: Node | Leaf) -> None:
            if isinstance(node, Node):
                for c in node.children:
                    at(c)
                if node is self.root and self.n > 1:
                    return
                seen[node.name] = view(node, [seen[c.name] for c in node.children])
            if node.name in self.engine.stored:
                self.engine.store.create(node.name, seen[node.name])

        at(self.root)
        if self.n > 1:
            sides = sorted(self.root.children, key=lambda c: "x1" not in c.keys)
            self.terms.append(tuple(seen[c.name] for c in sides))
            #: Whether the inner side is read from the first factors: from a matrix, where one is, as a view would be made twice.
            self.by_first = isinstance(sides[0], Leaf)

    def product(self) -> DataFrame:
        """(x1, x of the other end, v) of the cells that are not zero."""
        first, last = self.ends
        if self.n == 1:
            return self.engine.result().df.select(first, last, "v")
        if self.kind in ("long", "double"):
            left, right = self._stacked()
            out = multiplied(left.toDF("i", "k", "v"), right.toDF("j", "k", "v"), self.kind, self.by_first)
            if out is not None:
                return out.toDF(first, last, "v")
        whole = FactoredDelta(tuple(Term(self._paired(a, b)) for a, b in self.terms)).expand(self.ends)
        return whole.df.select(first, last, "v").where("v <> 0")

    def _paired(self, a: KeyedRelation, b: KeyedRelation) -> tuple[KeyedRelation, ...]:
        """Two relations that share their inner index as factors: already multiplied."""
        both = join(a, b)
        return (marginalize(both, [k for k in both.keys if k not in self.ends]),)

    def _stacked(self) -> tuple[DataFrame, DataFrame]:
        """All terms side by side, (end, k, v) each: k is the term's number with its inner index."""
        sides: list[DataFrame | None] = [None, None]
        for number, pair in enumerate(self.terms):
            for s, (rel, end) in enumerate(zip(pair, self.ends, strict=True)):
                one = rel.df.select(end, F.concat_ws(":", F.lit(number), *[k for k in rel.keys if k != end]).alias("k"), "v")
                sides[s] = one if sides[s] is None else sides[s].unionByName(one)
        return sides[0], sides[1]  # type: ignore[return-value]

    def _at_root(self, terms: Sequence[Term], sibling: KeyedRelation) -> list[Term]:
        """Changes of one side of the product, each as a pair of factors with the other side."""
        first, last = self.ends
        out = []
        for t in terms:
            if len(t.factors) == 1:  # not factored: the inner index is left for the product to sum
                out.append(Term((t.factors[0], sibling)))
            else:
                near = t.times([sibling])
                out.append(near.sum_away([v for v in near.keys if v not in (first, last, TERM)]))
        for t in out:
            a, b = sorted(t.factors, key=lambda f: last in f.keys)
            self.terms.append((self.engine.store._keep("term", a), self.engine.store._keep("term", b)))
        if len(self.terms) > WAITING:
            self._fold()
        return out

    def _fold(self) -> None:
        """The waiting products as one, with a longer inner side."""
        old, tables = self.terms, self._stacked()
        self.terms = [tuple(KeyedRelation(written(df, "terms").withColumn(COUNT, F.lit(1).cast("long")), (end, "k"), self.q.ring) for df, end in zip(tables, self.ends, strict=True))]
        for f in (f for pair in old for f in pair):
            f.df.unpersist()

    def update(self, i: int, delta: FactoredDelta, keep_factored: bool = False) -> FactoredDelta:
        """Low-rank change of the i-th matrix (from 0), keyed x(i+1), x(i+2); the answer is the product's change as pairs of
        factors.  They are part of the product from here on (with ``keep_factored`` too: nothing is multiplied out before)."""
        if self.n == 1:
            return apply_factored(self.engine, f"A{i + 1}", delta, keep_factored)
        return apply_factored(self.engine, f"A{i + 1}", delta, at_root=self._at_root)

    def update_dense(self, i: int, delta: DataFrame) -> None:
        """The contrast: the change as one relation, multiplied like a matrix."""
        a, b = f"x{i + 1}", f"x{i + 2}"
        rel = KeyedRelation(delta.select(F.col(delta.columns[0]).alias(a), F.col(delta.columns[1]).alias(b), F.col(delta.columns[2]).cast(self.kind).alias("v"), F.lit(1).cast("long").alias(COUNT)), (a, b), self.q.ring)
        self.update(i, FactoredDelta((Term((rel,)),)))

    def update_row(self, i: int, row: int, values: DataFrame) -> None:
        """Add ``values`` (column, v) to a row of the i-th matrix."""
        a, b = f"x{i + 1}", f"x{i + 2}"
        self.update(i, rank_one(self._unit(a, row), values.toDF(b, "v"), a, b, ring=self.q.ring))

    def update_column(self, i: int, column: int, values: DataFrame) -> None:
        """Add ``values`` (row, v) to a column of the i-th matrix."""
        a, b = f"x{i + 1}", f"x{i + 2}"
        self.update(i, rank_one(values.toDF(a, "v"), self._unit(b, column), a, b, ring=self.q.ring))

    def update_entry(self, i: int, row: int, column: int, value: float) -> None:
        self.update_row(i, row, self._unit("j", column, value))

    def _unit(self, name: str, at: int, value: float = 1) -> DataFrame:
        return F.broadcast(self.mats[0].sparkSession.createDataFrame([(at, value)], f"{name} long, v {'double' if isinstance(value, float) else 'long'}"))

    def state_size(self) -> int:
        """Stored values: views, and the factors of the product."""
        known = set(self.engine.store.names())
        return sum(self.engine.store.size(n) for n in self.engine.stored & known) + sum(f.size() for t in self.terms for f in t)


def matrix_chain(mats: Sequence[DataFrame], dims: Sequence[int], balanced: bool = False, ring: NumberRing | None = None) -> DataFrame:
    """The product from scratch, in the order with the fewest multiplications."""
    return MatrixChain(mats, dims, balanced, ring, updatable=()).product()


#: Blocks that a task of a product holds before it hands its sums on.
HELD = 64


class BlockMatrix:
    """Dense blocks of ``size`` x ``size`` doubles: (bi, bj, block).  ``rows`` (bi) and ``columns`` (bj) are the numbers that
    blocks can have, read without making a block."""

    SCHEMA = "bi long, bj long, block binary"

    def __init__(self, df: DataFrame, size: int, rows: DataFrame | None = None, columns: DataFrame | None = None):
        self.df, self.size = df, size
        self.rows = df.select("bi") if rows is None else rows
        self.columns = df.select("bj") if columns is None else columns

    @classmethod
    def of(cls, coo: DataFrame, size: int = 256) -> BlockMatrix:
        i, j, v = coo.columns

        def pack(pdf: pd.DataFrame) -> pd.DataFrame:
            m = _whole(pdf["piece"], size, size, "<f8")
            return pd.DataFrame({"bi": [pdf["bi"].iloc[0]], "bj": [pdf["bj"].iloc[0]], "block": [m.tobytes()]})

        cells = coo.select(F.col(i).cast("long").alias("i"), F.col(j).cast("long").alias("j"), F.col(v).cast("double").alias("v")).where("v is not null")
        at = lambda x: f"(({x} - pmod({x}, {size})) div {size}) AS b{x}"
        cells = cells.selectExpr(at("i"), at("j"), f"int(pmod(i, {size})) AS at", f"int(pmod(j, {size})) AS place", "v")
        return cls(_gathered(cells, ["bi", "bj"]).groupBy("bi", "bj").applyInPandas(pack, cls.SCHEMA), size, cells.select("bi"), cells.select("bj"))

    def __matmul__(self, other: BlockMatrix) -> BlockMatrix:
        size = self.size
        a = self.df.select("bi", F.col("bj").alias("k"), F.col("block").alias("a"))
        b = other.df.select(F.col("bi").alias("k"), "bj", F.col("block").alias("b"))

        def flush(sums: dict) -> pd.DataFrame:
            return pd.DataFrame({"bi": [k[0] for k in sums], "bj": [k[1] for k in sums], "block": [x.tobytes() for x in sums.values()]})

        def multiply(batches):
            """Products of a task, those of one cell summed as long as HELD blocks are not passed."""
            sums: dict[tuple[int, int], np.ndarray] = {}
            for p in batches:
                for i, j, x, y in zip(p["bi"], p["bj"], p["a"], p["b"], strict=True):
                    z = np.frombuffer(x).reshape(size, size) @ np.frombuffer(y).reshape(size, size)
                    sums[i, j] = sums[i, j] + z if (i, j) in sums else z
                    if len(sums) >= HELD:
                        yield flush(sums)
                        sums = {}
            if sums:
                yield flush(sums)

        def add(batches):
            """Blocks of a task, sorted by cell, summed one after another: memory for one sum."""
            at, total = None, None
            for p in batches:
                for i, j, x in zip(p["bi"], p["bj"], p["block"], strict=True):
                    if (i, j) != at:
                        if at is not None:
                            yield flush({at: total})
                        at, total = (i, j), np.zeros(size * size)
                    total = total + np.frombuffer(x)
            if at is not None:
                yield flush({at: total})

        inner = other.rows.distinct().limit(INNER // size + 1).collect()
        if len(inner) <= INNER // size:
            return BlockMatrix(self._by_strips(a, b, [max(1, x.distinct().limit(1 << 10).count()) for x in (self.rows, other.columns)]), size, self.rows, other.columns)
        parts = a.join(b, "k").select("bi", "bj", "a", "b").mapInPandas(multiply, self.SCHEMA)
        return BlockMatrix(parts.repartition("bi", "bj").sortWithinPartitions("bi", "bj").mapInPandas(add, self.SCHEMA), size, self.rows, other.columns)

    def _by_strips(self, a: DataFrame, b: DataFrame, most: Sequence[int]) -> DataFrame:
        """Rows of blocks times columns of blocks: each block of the product is made whole in one task, none is shuffled."""
        size = self.size
        strip = lambda df, x, block, n: _met(df.select(x, F.struct("k", F.col(block).alias("m")).alias(block)), x, block, n)

        def multiply(batches):
            for p in batches:
                for i, j, x, y in zip(p["bi"], p["bj"], p["a"], p["b"], strict=True):
                    right, total = {r["k"]: r["m"] for r in y}, None
                    for r in x:
                        if r["k"] in right:
                            z = np.frombuffer(r["m"]).reshape(size, size) @ np.frombuffer(right[r["k"]]).reshape(size, size)
                            total = z if total is None else total + z
                    if total is not None:
                        yield pd.DataFrame({"bi": [i], "bj": [j], "block": [total.tobytes()]})

        return strip(a, "bi", "a", most[0]).crossJoin(strip(b, "bj", "b", most[1])).mapInPandas(multiply, self.SCHEMA)

    def cells(self) -> DataFrame:
        """(i, j, v) of the entries that are not zero."""
        size = self.size

        def unpack(batches):
            for p in batches:
                for bi, bj, block in zip(p["bi"], p["bj"], p["block"], strict=True):
                    m = np.frombuffer(block).reshape(size, size)
                    i, j = np.nonzero(m)
                    yield pd.DataFrame({"i": i + bi * size, "j": j + bj * size, "v": m[i, j]})

        return self.df.mapInPandas(unpack, "i long, j long, v double")
