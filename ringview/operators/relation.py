"""Relations over rings: each key has one payload, and keys with a zero payload are absent."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Row
from pyspark.sql import functions as F

from ringview.functions.rings import LongRing, Payload, Ring

#: Multiplicity column of a signed bag: +1 for an insert, -1 for a delete.
SIGN = "__m"
#: Number of the batch that a change came with, where changes of several batches are in one table.
AT = "__at"
#: Number of derivations behind an entry; tells a zero payload from rounding dust.
COUNT = "__n"
#: Largest absolute value of a floating-point slot that counts as zero when nothing stands behind it.
DUST = 1e-9


@dataclass(frozen=True)
class KeyedRelation:
    """``df`` has the columns ``keys``, the ring's slots that are not zero, and COUNT."""

    df: DataFrame
    keys: tuple[str, ...]
    ring: Ring

    @property
    def slots(self) -> tuple[str, ...]:
        return tuple(c for c in self.df.columns if c not in self.keys and c not in (COUNT, AT) and c not in self.inner)

    @property
    def inner(self) -> tuple[str, ...]:
        return self.ring.inner if isinstance(self.ring, LongRing) else ()

    def payload(self, prefix: str = "") -> Payload:
        return {s: F.col(f"{prefix}{s}") for s in self.slots}

    @classmethod
    def from_bag(cls, df: DataFrame, keys: Sequence[str], ring: Ring) -> KeyedRelation:
        """A bag, signed or not: each row is worth the ring's one, times its sign."""
        return aggregate(df if SIGN in df.columns else df.withColumn(SIGN, F.lit(1)), tuple(keys), {}, ring)

    def size(self) -> int:
        return self.df.count()

    def contains(self, **key: object) -> bool:
        return not self.slice(**key).isEmpty()

    def slice(self, **key: object) -> DataFrame:
        """Rows with these values of some keys."""
        df = self.df
        for k, v in key.items():
            df = df.where(F.col(k).eqNullSafe(F.lit(v)))
        return df

    def enumerate(self) -> Iterator[Row]:
        return self.df.toLocalIterator()


def _nonzero(df: DataFrame, keys: tuple[str, ...], ring: Ring, slots: Sequence[str]) -> DataFrame:
    """Drop entries without derivations whose payload is zero as well (signed bags may cancel in number only); dust of
    floating-point sums counts as zero, and semirings go by the number."""
    gone = F.col(COUNT) == 0
    if slots and ring.inverse:
        small = [F.abs(F.col(s)) <= DUST if k in ("double", "float") else F.col(s) == 0 for s, k in df.select(*slots).dtypes]
        for x in small:
            gone = gone & x
    return df.where(~gone)


def _sum(rows: DataFrame, keys: tuple[str, ...], ring: Ring, slots: Sequence[str]) -> DataFrame:
    inner = ring.inner if isinstance(ring, LongRing) else ()
    aggs = [ring.total(s, F.col(s)).alias(s) for s in slots] + [F.sum(COUNT).cast(count_type(ring)).alias(COUNT)]
    by = [*keys, *inner]
    out = rows.groupBy(*by).agg(*aggs) if by else rows.agg(*aggs).where(F.col(COUNT).isNotNull())
    return _nonzero(out, keys, ring, slots)


def count_type(ring: Ring) -> str:
    """Derivations are counted as widely as the ring's own numbers."""
    ring = getattr(ring, "of_tuples", ring)
    return "decimal(38,0)" if getattr(ring, "type_name", "").startswith("decimal(38") else "long"


def aggregate(bag: DataFrame, keys: tuple[str, ...], lift: dict[str, Column], ring: Ring) -> KeyedRelation:
    """Straight from a signed bag: lift the variables of ``lift`` and sum per key, one pass for a whole chain."""
    n = F.col(SIGN).cast(count_type(ring))
    if isinstance(ring, LongRing):
        rel = KeyedRelation(bag.select(*keys, *lift, *[c.alias(k) for k, c in (ring.unit() | ring.copies(n)).items()], n.alias(COUNT)), keys + tuple(lift), ring)
        return marginalize(rel, tuple(lift))
    each = getattr(ring, "of_tuples", ring)
    payload = each.one()
    for var, col in lift.items():
        payload = each.mul(payload, each.lift(var, col))
    payload = each.scale(payload, n)
    rows = bag.select(*keys, *[c.alias(s) for s, c in payload.items()], n.alias(COUNT))
    return KeyedRelation(_sum(rows, keys, each, list(payload)), keys, ring)


def marginalize(a: KeyedRelation, variables: Sequence[str], lifted: bool = True) -> KeyedRelation:
    """Sum variables away; with ``lifted`` each entry is first multiplied by the lift of its values."""
    ring, keys = a.ring, tuple(k for k in a.keys if k not in variables)
    gone = [v for v in a.keys if v in variables]
    if isinstance(ring, LongRing):
        df = a.df
        for v in gone:
            if not lifted:
                continue
            left, right = {c: F.col(c) for c in (*ring.inner, *ring.slots)}, {c: F.col(f"__l.{c}") for c in (*ring.inner, *ring.slots)}
            single = ring.lift_row(v, F.col(v))
            if single is not None:
                if single:
                    inner, _ = ring.combine(left, single)
                    df = df.select(*[c for c in df.columns if c not in left and c != COUNT], *[c.alias(k) for k, c in (inner | ring.times(left, single)).items()], COUNT)
                continue
            rows = df.withColumn("__l", F.explode(ring.lift_rows(v, F.col(v))))
            inner, keep = ring.combine(left, right)
            rows = rows if keep is None else rows.where(keep)
            others = [c for c in df.columns if c not in ring.inner and c not in (*ring.slots, COUNT)]
            df = rows.select(*others, *[c.alias(k) for k, c in (inner | ring.times(left, right)).items()], COUNT)
        rows = df.select(*keys, *ring.inner, *ring.slots, COUNT)
        return KeyedRelation(_sum(rows, keys, ring, ring.slots), keys, ring)
    payload = a.payload()
    for v in gone:
        payload = ring.mul(payload, ring.lift(v, F.col(v))) if lifted else payload
    rows = a.df.select(*keys, *[c.alias(s) for s, c in payload.items()], COUNT)
    return KeyedRelation(_sum(rows, keys, ring, list(payload)), keys, ring)


def union(*parts: KeyedRelation) -> KeyedRelation:
    """Sum of payloads."""
    ring, keys = parts[0].ring, parts[0].keys
    inner = parts[0].inner
    slots = sorted({s for p in parts for s in p.slots})
    rows = None
    for p in parts:
        have = set(p.slots)
        df = p.df.select(*keys, *inner, *[F.col(s) if s in have else ring.zero_slot(s).alias(s) for s in slots], COUNT)
        rows = df if rows is None else rows.unionByName(df)
    return KeyedRelation(_sum(rows, keys, ring, slots), keys, ring)


def join(a: KeyedRelation, b: KeyedRelation, hint: str | None = None, total: bool = True) -> KeyedRelation:
    """Product of payloads on equal shared keys; ``hint`` 'broadcast' for a small right side.  Without ``total`` rows of
    a long payload are left for a later sum to unite."""
    ring = a.ring
    shared = [k for k in a.keys if k in b.keys]
    right = b.df.select(*[F.col(c) if c in shared else F.col(c).alias(c if c in b.keys else f"__r_{c}") for c in b.df.columns])
    right = F.broadcast(right) if hint == "broadcast" else right
    both = a.df.join(right, shared) if shared else a.df.crossJoin(right)
    keys = a.keys + tuple(k for k in b.keys if k not in a.keys)
    count = (F.col(COUNT) * F.col(f"__r_{COUNT}")).cast(count_type(ring)).alias(COUNT)
    if isinstance(ring, LongRing):
        left, other = {c: F.col(c) for c in (*ring.inner, *ring.slots)}, {c: F.col(f"__r_{c}") for c in (*ring.inner, *ring.slots)}
        inner, keep = ring.combine(left, other)
        both = both if keep is None else both.where(keep)
        rows = both.select(*keys, *[c.alias(k) for k, c in (inner | ring.times(left, other)).items()], count)
        return KeyedRelation(_sum(rows, keys, ring, ring.slots) if total else rows, keys, ring)
    payload = ring.mul(a.payload(), b.payload("__r_"))
    return KeyedRelation(both.select(*keys, *[c.alias(s) for s, c in payload.items()], count), keys, ring)


def without_number(a: KeyedRelation) -> KeyedRelation:
    """The change of all its batches: a key has as many rows as batches changed it, and a union sums them."""
    return KeyedRelation(a.df, tuple(k for k in a.keys if k != AT), a.ring)


def join_as_of(change: KeyedRelation, old: KeyedRelation, moved: KeyedRelation | None, first: int, last: int, left: bool = False) -> KeyedRelation:
    """Join of a numbered change with what the other side was before each batch: ``old``, and the changes ``moved`` with a
    smaller number (all numbers are from ``first`` to ``last``; ``left``: the other side is the left factor).

    The numbers below one are a few blocks of 1, 2, 4, ... numbers, so a row meets sums of blocks, not each earlier change.
    """
    meet = lambda a, b: join(b, a, total=False) if left else join(a, b, total=False)
    now = meet(change, old)
    if moved is None:
        return now
    levels, i, block = (last - first).bit_length(), F.col(AT) - F.lit(first), "__block"
    code = lambda k, level: k * 64 + F.lit(level)
    whole = F.explode(F.array(*[code(F.shiftright(i, n), n) for n in range(levels)]))
    below = F.explode(F.array_compact(F.array(*[F.when(F.shiftright(i, n) % 2 == 1, code(F.shiftright(i, n) - 1, n)) for n in range(levels)])))
    if not levels:
        return now
    sums = marginalize(KeyedRelation(moved.df.withColumn(block, whole), (*moved.keys, block), moved.ring), [AT], lifted=False)
    before = marginalize(meet(KeyedRelation(change.df.withColumn(block, below), (*change.keys, block), change.ring), sums), [block], lifted=False)
    return union(now, before)


def negate(a: KeyedRelation) -> KeyedRelation:
    payload = {s: -F.col(s) for s in a.slots} if isinstance(a.ring, LongRing) else a.ring.neg(a.payload())
    return KeyedRelation(a.df.select(*a.keys, *a.inner, *[c.alias(s) for s, c in payload.items()], (-F.col(COUNT)).alias(COUNT)), a.keys, a.ring)


def indicator(a: KeyedRelation, onto: Sequence[str], ring: Ring | None = None) -> KeyedRelation:
    """One for each value of ``onto`` that has an entry; ``support`` counts them."""
    ring = ring or a.ring
    df = a.df.select(*onto).distinct()
    extra = ring.unit() | ring.copies(F.lit(1).cast("long")) if isinstance(ring, LongRing) else ring.one()
    return KeyedRelation(df.select(*onto, *[c.alias(s) for s, c in extra.items()], F.lit(1).cast("long").alias(COUNT)), tuple(onto), ring)


def support(a: KeyedRelation, onto: Sequence[str]) -> DataFrame:
    """(onto, n): how many entries stand behind each value."""
    return a.df.groupBy(*onto).agg(F.count("*").alias("n"))


def support_change(old: DataFrame, entering: DataFrame, leaving: DataFrame, onto: Sequence[str]) -> DataFrame:
    """(onto, __m in {1, -1}): values whose support rises from zero, or falls to it.  ``old``: (onto, n); ``entering``
    and ``leaving``: keys that become non-zero, or zero."""
    step = entering.select(*onto, F.lit(1).alias("d")).unionByName(leaving.select(*onto, F.lit(-1).alias("d")))
    moved = step.groupBy(*onto).agg(F.sum("d").alias("d")).where("d <> 0").join(old, list(onto), "left").withColumn("n", F.coalesce("n", F.lit(0)))
    sign = F.when((F.col("n") == 0) & (F.col("d") > 0), 1).when((F.col("n") > 0) & (F.col("n") + F.col("d") <= 0), -1)
    return moved.withColumn(SIGN, sign).where(F.col(SIGN).isNotNull()).select(*onto, SIGN)


def indicator_difference(before: KeyedRelation, after: KeyedRelation, onto: Sequence[str]) -> DataFrame:
    """(onto, __m in {1, -1}): the same change as by supports, from both contents whole."""
    side = lambda a, n: a.df.select(*onto).distinct().withColumn(SIGN, F.lit(n))
    return side(after, 1).unionByName(side(before, -1)).groupBy(*onto).agg(F.sum(SIGN).alias(SIGN)).where(F.col(SIGN) != 0)
