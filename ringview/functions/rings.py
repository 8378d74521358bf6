"""Rings and semirings as builders of column expressions.

A payload is a dict from slot name to column; a slot that is absent is zero.  A ring says how two payloads are
multiplied, which aggregate sums each slot, what one, minus and "is zero" are, and how a variable's value is lifted.
Catalyst sees plain expressions only.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

Payload = dict[str, Column]


def _plus(terms: Sequence[Column]) -> Column:
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return out


class Ring:
    """Interface.  ``commutative``: the order of factors does not matter.  ``inverse``: there are negative payloads."""

    commutative = True
    inverse = True
    slots: tuple[str, ...] = ("v",)

    def one(self) -> Payload:
        raise NotImplementedError

    def mul(self, a: Payload, b: Payload) -> Payload:
        raise NotImplementedError

    def total(self, slot: str, column: Column) -> Column:
        """Aggregate that sums a slot."""
        return F.sum(column)

    def neg(self, a: Payload) -> Payload:
        if not self.inverse:
            raise ValueError(f"{type(self).__name__} has no additive inverse: insert only")
        return {k: -v for k, v in a.items()}

    def scale(self, a: Payload, n: Column) -> Payload:
        """n copies of a payload, n a whole number."""
        return {k: v * n for k, v in a.items()}

    def lift(self, var: str, value: Column) -> Payload:
        return self.one()

    def is_zero(self, a: Payload) -> Column:
        out = F.lit(True)
        for v in a.values():
            out = out & (v == 0)
        return out

    def zero(self) -> Payload:
        return {}

    def zero_slot(self, slot: str) -> Column:
        """What a slot that one operand lacks is filled with."""
        return F.lit(0)


@dataclass(frozen=True)
class NumberRing(Ring):
    """Numbers of one SQL type.  Variables named in ``lifts`` count with their value, others with 1."""

    type_name: str = "long"
    lifts: tuple[str, ...] = ()

    @property
    def of_tuples(self) -> NumberRing:
        """The ring that values of single tuples are in until they are first summed."""
        return self

    def one(self) -> Payload:
        return {"v": F.lit(1).cast(self.type_name)}

    def mul(self, a: Payload, b: Payload) -> Payload:
        if "v" not in a or "v" not in b:
            return {}
        return {"v": (a["v"] * b["v"]).cast(self.type_name)}

    def total(self, slot: str, column: Column) -> Column:
        return F.sum(column).cast(self.type_name)

    def scale(self, a: Payload, n: Column) -> Payload:
        return {k: (v * n).cast(self.type_name) for k, v in a.items()}

    def lift(self, var: str, value: Column) -> Payload:
        return {"v": value.cast(self.type_name)} if var in self.lifts else self.one()


def IntRing(*lifts: str) -> NumberRing:
    return NumberRing("long", lifts)


def BigIntRing(*lifts: str) -> NumberRing:
    """Whole numbers of 38 digits; overflow is an error."""
    return NumberRing("decimal(38,0)", lifts)


def RealRing(*lifts: str) -> NumberRing:
    return NumberRing("double", lifts)


def FixedRing(scale: int, *lifts: str) -> NumberRing:
    return NumberRing(f"decimal(38,{scale})", lifts)


@dataclass(frozen=True)
class ComplexRing(Ring):
    slots = ("re", "im")
    lifts: tuple[str, ...] = ()

    def one(self) -> Payload:
        return {"re": F.lit(1.0), "im": F.lit(0.0)}

    def mul(self, a: Payload, b: Payload) -> Payload:
        return {"re": a["re"] * b["re"] - a["im"] * b["im"], "im": a["re"] * b["im"] + a["im"] * b["re"]}


@dataclass(frozen=True)
class NatSemiring(NumberRing):
    inverse = False


@dataclass(frozen=True)
class MaxProductSemiring(Ring):
    """Numbers from 0 up with max as sum."""

    inverse = False
    lifts: tuple[str, ...] = ()

    def one(self) -> Payload:
        return {"v": F.lit(1.0)}

    def mul(self, a: Payload, b: Payload) -> Payload:
        return {"v": a["v"] * b["v"]}

    def total(self, slot: str, column: Column) -> Column:
        return F.max(column)

    def scale(self, a: Payload, n: Column) -> Payload:
        return {"v": F.when(n > 0, a["v"]).otherwise(F.when(n == 0, F.lit(0.0)).otherwise(F.raise_error(F.lit("insert only"))))}

    def lift(self, var: str, value: Column) -> Payload:
        return {"v": value.cast("double")} if var in self.lifts else self.one()


@dataclass(frozen=True)
class BoolSemiring(Ring):
    inverse = False

    def one(self) -> Payload:
        return {"v": F.lit(True)}

    def mul(self, a: Payload, b: Payload) -> Payload:
        return {"v": a["v"] & b["v"]}

    def total(self, slot: str, column: Column) -> Column:
        return F.bool_or(column)

    def scale(self, a: Payload, n: Column) -> Payload:
        return {"v": a["v"] & F.when(n >= 0, n > 0).otherwise(F.raise_error(F.lit("insert only")))}

    def is_zero(self, a: Payload) -> Column:
        return ~a["v"]

    def zero_slot(self, slot: str) -> Column:
        return F.lit(False)


@dataclass(frozen=True)
class SetSemiring(Ring):
    """Sets with union as sum and intersection as product; ``all`` marks the universe."""

    inverse = False
    slots = ("all", "v")
    lifts: tuple[str, ...] = ()

    def one(self) -> Payload:
        return {"all": F.lit(True), "v": F.array().cast("array<string>")}

    def mul(self, a: Payload, b: Payload) -> Payload:
        v = F.when(a["all"], b["v"]).when(b["all"], a["v"]).otherwise(F.array_intersect(a["v"], b["v"]))
        return {"all": a["all"] & b["all"], "v": v}

    def total(self, slot: str, column: Column) -> Column:
        return F.bool_or(column) if slot == "all" else F.array_sort(F.array_distinct(F.flatten(F.collect_list(column))))

    def scale(self, a: Payload, n: Column) -> Payload:
        return {"all": a["all"] & (n > 0), "v": F.when(n > 0, a["v"]).otherwise(F.array().cast("array<string>"))}

    def lift(self, var: str, value: Column) -> Payload:
        return {"all": F.lit(False), "v": F.array(value.cast("string"))} if var in self.lifts else self.one()

    def is_zero(self, a: Payload) -> Column:
        return ~a["all"] & (F.size(a["v"]) == 0)

    def zero_slot(self, slot: str) -> Column:
        return F.lit(False) if slot == "all" else F.array().cast("array<string>")


@dataclass(frozen=True)
class MatrixRing(Ring):
    """n x n matrices of doubles, one slot an entry.  Not commutative."""

    n: int = 2
    commutative = False

    @property
    def slots(self) -> tuple[str, ...]:  # type: ignore[override]
        return tuple(f"m{i}_{j}" for i in range(self.n) for j in range(self.n))

    def one(self) -> Payload:
        return {f"m{i}_{j}": F.lit(float(i == j)) for i in range(self.n) for j in range(self.n)}

    def mul(self, a: Payload, b: Payload) -> Payload:
        r = range(self.n)
        return {f"m{i}_{j}": _plus([a[f"m{i}_{k}"] * b[f"m{k}_{j}"] for k in r]) for i in r for j in r}


@dataclass(frozen=True)
class CovarianceRing(Ring):
    """(count, sums, sums of products) over ``vars``: slots cnt, s_x and q_x_y with x <= y, of any number ring ``over``.

    Slots of variables outside a view's part of the tree are absent, so payloads grow towards the root.
    """

    vars: tuple[str, ...] = ()
    over: NumberRing = field(default_factory=lambda: NumberRing("double"))

    @staticmethod
    def q(x: str, y: str) -> str:
        return f"q_{min(x, y)}_{max(x, y)}"

    @property
    def slots(self) -> tuple[str, ...]:  # type: ignore[override]
        v = sorted(self.vars)
        return ("cnt", *(f"s_{x}" for x in v), *(self.q(x, y) for i, x in enumerate(v) for y in v[i:]))

    def one(self) -> Payload:
        return {"cnt": self.over.one()["v"]}

    def mul(self, a: Payload, b: Payload) -> Payload:
        terms: dict[str, list[Column]] = {}
        put = lambda k, x, y: terms.setdefault(k, []).append(x * y)
        if "cnt" in a and "cnt" in b:
            put("cnt", a["cnt"], b["cnt"])
        for p, r in ((a, b), (b, a)):
            for k, v in p.items():
                if k != "cnt" and "cnt" in r:
                    put(k, v, r["cnt"])
        for x in self.vars:
            for y in self.vars:
                if f"s_{x}" in a and f"s_{y}" in b:
                    for _ in range(1 + (x == y)):  # the diagonal takes the cross product twice
                        put(self.q(x, y), a[f"s_{x}"], b[f"s_{y}"])
        return {k: _plus(v) for k, v in terms.items()}

    def total(self, slot: str, column: Column) -> Column:
        return F.sum(column).cast(self.over.type_name)

    def scale(self, a: Payload, n: Column) -> Payload:
        return {k: v * n for k, v in a.items()}

    def lift(self, var: str, value: Column) -> Payload:
        if var not in self.vars:
            return self.one()
        x = value.cast(self.over.type_name)
        return self.one() | {f"s_{var}": x, self.q(var, var): x * x}


@dataclass(frozen=True)
class ProductRing(Ring):
    """Several rings side by side; slots carry the part's name."""

    parts: tuple[tuple[str, Ring], ...] = ()

    @property
    def inverse(self) -> bool:  # type: ignore[override]
        return all(r.inverse for _, r in self.parts)

    @property
    def slots(self) -> tuple[str, ...]:  # type: ignore[override]
        return tuple(f"{n}__{s}" for n, r in self.parts for s in r.slots)

    def _each(self, f, *payloads: Payload) -> Payload:
        return {f"{n}__{k}": v for n, r in self.parts for k, v in f(r, *[{s[len(n) + 2 :]: c for s, c in p.items() if s.startswith(f"{n}__")} for p in payloads]).items()}

    def one(self) -> Payload:
        return self._each(lambda r: r.one())

    def mul(self, a: Payload, b: Payload) -> Payload:
        return self._each(lambda r, x, y: r.mul(x, y), a, b)

    def scale(self, a: Payload, n: Column) -> Payload:
        return self._each(lambda r, x: r.scale(x, n), a)

    def neg(self, a: Payload) -> Payload:
        return self._each(lambda r, x: r.neg(x), a)

    def lift(self, var: str, value: Column) -> Payload:
        return self._each(lambda r: r.lift(var, value))

    def _of(self, slot: str) -> tuple[Ring, str]:
        n, s = slot.split("__", 1)
        return dict(self.parts)[n], s

    def total(self, slot: str, column: Column) -> Column:
        r, s = self._of(slot)
        return r.total(s, column)

    def is_zero(self, a: Payload) -> Column:
        out = F.lit(True)
        for n, r in self.parts:
            out = out & r.is_zero({s[len(n) + 2 :]: c for s, c in a.items() if s.startswith(f"{n}__")})
        return out

    def zero_slot(self, slot: str) -> Column:
        r, s = self._of(slot)
        return r.zero_slot(s)


class LongRing(Ring):
    """Payloads that are relations: rows beside the keys, with ``inner`` columns and a multiplicity or value ``v``; a ring
    may have more slots than that.

    A product pairs the rows of two payloads; ``combine`` gives its inner columns and which pairs count, ``times`` its slots.
    """

    inner: tuple[str, ...] = ()
    slots = ("v",)

    def combine(self, a: Mapping[str, Column], b: Mapping[str, Column]) -> tuple[dict[str, Column], Column | None]:
        raise NotImplementedError

    def lift_rows(self, var: str, value: Column) -> Column:
        """Array of structs (inner columns, v): the rows of a lifted value."""
        raise NotImplementedError

    def lift_row(self, var: str, value: Column) -> dict[str, Column] | None:
        """The row of a lifted value, if it never has more than one (empty: the unit); else None."""
        return None

    def weight(self, a: Mapping[str, Column], b: Mapping[str, Column]) -> Column:
        return F.lit(1)

    def times(self, a: Mapping[str, Column], b: Mapping[str, Column]) -> Payload:
        """Slots of a product of two rows; ``a`` and ``b`` have inner columns and slots."""
        return {"v": a["v"] * b["v"] * self.weight(a, b)}

    def copies(self, n: Column) -> Payload:
        """Slots of n times the unit."""
        return {"v": n}

    def unit(self) -> dict[str, Column]:
        raise NotImplementedError


@dataclass(frozen=True)
class RelationalRing(LongRing):
    """Relations over whole numbers with union and join.  Values of ``free`` variables are kept, others are counted.
    With ``factorized`` a payload keeps the variable of its own view only; the rest is in the views below."""

    free: tuple[str, ...] = ()
    factorized: bool = False

    @property
    def inner(self) -> tuple[str, ...]:  # type: ignore[override]
        return tuple(f"p_{x}" for x in self.free)

    def unit(self) -> dict[str, Column]:
        return {x: F.lit(None).cast("string") for x in self.inner}

    def combine(self, a, b):
        return {x: F.coalesce(a[x], b[x]) for x in self.inner}, None

    def lift_rows(self, var: str, value: Column) -> Column:
        row = [(value if x == var else F.lit(None)).cast("string").alias(f"p_{x}") for x in self.free]
        return F.array(F.struct(*row, F.lit(1).cast("long").alias("v")))


@dataclass(frozen=True)
class GenCovarianceRing(LongRing):
    """Covariance over continuous and categorical variables: rows (x, cx, y, cy, v) with x <= y; an empty name says that
    the place is not taken, cx and cy are the categories (empty for continuous variables).  The degree of a row is the
    number of its variables; a product keeps degrees up to 2."""

    cont: tuple[str, ...] = ()
    cat: tuple[str, ...] = ()
    type_name: str = "long"
    inner = ("x", "cx", "y", "cy")

    def unit(self) -> dict[str, Column]:
        return {c: F.lit("") for c in self.inner}

    def combine(self, a, b):
        deg = lambda p: (p["x"] != "").cast("int") + (p["y"] != "").cast("int")
        first = lambda p: F.struct(p["x"].alias("x"), p["cx"].alias("c"))
        # of the degrees (0,k) and (k,0) one operand's row stays; two of degree 1 meet, the smaller name first
        lo, hi = F.least(first(a), first(b)), F.greatest(first(a), first(b))
        both = (a["x"] != "") & (b["x"] != "")
        pick = lambda c: F.when(a["x"] == "", b[c]).otherwise(a[c])
        out = {"x": F.when(both, lo["x"]).otherwise(pick("x")), "cx": F.when(both, lo["c"]).otherwise(pick("cx")), "y": F.when(both, hi["x"]).otherwise(pick("y")), "cy": F.when(both, hi["c"]).otherwise(pick("cy"))}
        return out, deg(a) + deg(b) <= 2

    def weight(self, a, b):
        """The diagonal takes a cross product twice."""
        return F.when((a["x"] != "") & (a["x"] == b["x"]) & (a["cx"] == b["cx"]) & (a["y"] == "") & (b["y"] == ""), 2).otherwise(1)

    def lift_rows(self, var: str, value: Column) -> Column:
        row = lambda x, cx, y, cy, v: F.struct(F.lit(x).alias("x"), cx.alias("cx"), F.lit(y).alias("y"), cy.alias("cy"), v.cast(self.type_name).alias("v"))
        none, one = F.lit(""), F.lit(1)
        rows = [row("", none, "", none, one)]
        if var in self.cont:
            rows += [row(var, none, "", none, value), row(var, none, var, none, value.cast(self.type_name) * value.cast(self.type_name))]
        elif var in self.cat:
            c = value.cast("string")
            rows += [row(var, c, "", none, one), row(var, c, var, c, one)]
        return F.array(*rows)


@dataclass(frozen=True)
class HybridCovarianceRing(GenCovarianceRing):
    """The generalized covariance with scalars wherever categories need no rows of their own.

    Inner columns name categorical variables only, ``v`` counts.  The row without categories carries sums ``s_`` and
    products ``q_`` of the continuous variables, a row of one category carries their sums in it, a row of two only counts.
    """

    @property
    def slots(self) -> tuple[str, ...]:  # type: ignore[override]
        v = sorted(self.cont)
        return ("v", *(f"s_{x}" for x in v), *(CovarianceRing.q(x, y) for i, x in enumerate(v) for y in v[i:]))

    def times(self, a, b):
        open_ = lambda p, c: p[c] == ""
        plain = open_(a, "x") & open_(b, "x")
        single = open_(a, "y") & open_(b, "y") & (open_(a, "x") | open_(b, "x"))
        when = lambda cond, value: F.when(cond, value).otherwise(F.lit(0)).cast(self.type_name)
        out = {"v": a["v"] * b["v"] * self.weight(a, b)}
        v = sorted(self.cont)
        for i, x in enumerate(v):
            out[f"s_{x}"] = when(single, a[f"s_{x}"] * b["v"] + a["v"] * b[f"s_{x}"])
            for y in v[i:]:
                q = CovarianceRing.q(x, y)
                out[q] = when(plain, a[q] * b["v"] + a["v"] * b[q] + a[f"s_{x}"] * b[f"s_{y}"] + a[f"s_{y}"] * b[f"s_{x}"])
        return out

    def copies(self, n: Column) -> Payload:
        return {s: (n if s == "v" else F.lit(0)).cast(self.type_name) for s in self.slots}

    def lift_rows(self, var: str, value: Column) -> Column:
        def row(x: str, cx: Column, y: str, cy: Column, **filled: Column) -> Column:
            return F.struct(
                F.lit(x).alias("x"), cx.alias("cx"), F.lit(y).alias("y"), cy.alias("cy"), F.lit(1).cast(self.type_name).alias("v"),
                *[filled.get(s, F.lit(0)).cast(self.type_name).alias(s) for s in self.slots if s != "v"],
            )

        none = F.lit("")
        if var in self.cont:
            n = value.cast(self.type_name)
            return F.array(row("", none, "", none, **{f"s_{var}": n, CovarianceRing.q(var, var): n * n}))
        rows = [row("", none, "", none)]
        if var in self.cat:
            c = value.cast("string")
            rows += [row(var, c, "", none), row(var, c, var, c)]
        return F.array(*rows)


@dataclass(frozen=True)
class JointCovarianceRing(LongRing):
    """The generalized covariance before pairs are listed: a row for each combination of categories that occurs, with its
    count ``v``, sums ``s_`` and products ``q_`` of the continuous variables.

    A view has at most one row for each tuple below it, while the long layout has one for each pair of variables; the
    latter is the sum over these rows (``long_rows``), so it is taken once, from the result.  A null inner column is a
    category that is null, or one that is not in the view's part of the tree.
    """

    cont: tuple[str, ...] = ()
    cat: tuple[str, ...] = ()
    type_name: str = "long"

    @property
    def inner(self) -> tuple[str, ...]:  # type: ignore[override]
        return tuple(f"c_{x}" for x in sorted(self.cat))

    @property
    def slots(self) -> tuple[str, ...]:  # type: ignore[override]
        v = sorted(self.cont)
        return ("v", *(f"s_{x}" for x in v), *(CovarianceRing.q(x, y) for i, x in enumerate(v) for y in v[i:]))

    def unit(self) -> dict[str, Column]:
        return {x: F.lit(None).cast("string") for x in self.inner}

    def combine(self, a, b):
        return {x: F.coalesce(a[x], b[x]) for x in self.inner}, None

    def times(self, a, b):
        out, v = {"v": (a["v"] * b["v"]).cast(self.type_name)}, sorted(self.cont)
        for i, x in enumerate(v):
            out[f"s_{x}"] = (a[f"s_{x}"] * b["v"] + a["v"] * b[f"s_{x}"]).cast(self.type_name)
            for y in v[i:]:
                q = CovarianceRing.q(x, y)
                out[q] = (a[q] * b["v"] + a["v"] * b[q] + a[f"s_{x}"] * b[f"s_{y}"] + a[f"s_{y}"] * b[f"s_{x}"]).cast(self.type_name)
        return out

    def copies(self, n: Column) -> Payload:
        return {s: (n if s == "v" else F.lit(0)).cast(self.type_name) for s in self.slots}

    def lift_row(self, var: str, value: Column) -> dict[str, Column] | None:
        if var not in self.cont and var not in self.cat:
            return {}
        n = value.cast(self.type_name)
        filled = {"v": F.lit(1)} | ({f"s_{var}": n, CovarianceRing.q(var, var): n * n} if var in self.cont else {})
        row = {x: (value if f"c_{var}" == x else F.lit(None)).cast("string") for x in self.inner}
        return row | {s: filled.get(s, F.lit(0)).cast(self.type_name) for s in self.slots}

    def lift_rows(self, var: str, value: Column) -> Column:
        row = self.lift_row(var, value) or self.unit() | self.copies(F.lit(1))
        return F.array(F.struct(*[c.alias(k) for k, c in row.items()]))
