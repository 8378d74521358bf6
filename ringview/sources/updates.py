"""Update streams: signed bags, batches, round robin."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringview.operators.relation import AT, SIGN

Batch = tuple[str, DataFrame]


def signed(df: DataFrame, op: str | Column | None = None, delete: str = "D") -> DataFrame:
    """+1 for inserts, -1 for rows whose operation is ``delete``."""
    if op is None:
        return df.withColumn(SIGN, F.lit(1))
    col = F.col(op) if isinstance(op, str) else op
    out = df.withColumn(SIGN, F.when(col == delete, -1).otherwise(1))
    return out.drop(op) if isinstance(op, str) else out


def inserts(df: DataFrame) -> DataFrame:
    return df.withColumn(SIGN, F.lit(1))


def deletes(df: DataFrame) -> DataFrame:
    return df.withColumn(SIGN, F.lit(-1))


def split(df: DataFrame, key: str | Column, first: int = 7, of: int = 10) -> tuple[DataFrame, list[DataFrame]]:
    """Initial rows (key mod ``of`` below ``first``) and one batch for each further residue."""
    r = F.pmod(F.col(key) if isinstance(key, str) else key, F.lit(of))
    return df.where(r < first), [inserts(df.where(r == i)) for i in range(first, of)]


def round_robin(batches: dict[str, Sequence[DataFrame]]) -> Iterator[Batch]:
    """One batch of each relation in turn."""
    for i in range(max(map(len, batches.values()), default=0)):
        for r, b in batches.items():
            if i < len(b):
                yield r, b[i]


def turns(batches: dict[str, int]) -> list[str]:
    """The relation of each batch of ``round_robin``, by how many batches each relation has."""
    return [r for i in range(max(batches.values(), default=0)) for r, n in batches.items() if i < n]


def turn(batches: dict[str, int], relation: str, own: Column) -> Column:
    """Place in ``turns`` of a relation's ``own``-th batch."""
    names = list(batches)
    before = [F.least(own, F.lit(n)) + (own < n).cast("long") * int(names.index(r) < names.index(relation)) for r, n in batches.items() if r != relation]
    return sum(before, own).cast("long").alias(AT)


def numbered(df: DataFrame, order: Sequence[str], size: int) -> DataFrame:
    """Batch numbers of ``size`` rows along ``order``: ranges are sorted apart and offset by their counts."""
    spark = df.sparkSession
    parts = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__p", F.spark_partition_id()).withColumn("__i", F.monotonically_increasing_id() % F.lit(1 << 33))
    from pyspark.sql.window import Window

    counts = parts.groupBy("__p").count()
    offset = counts.withColumn("__o", F.coalesce(F.sum("count").over(Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("count")
    assert spark is not None
    return parts.join(F.broadcast(offset), "__p").withColumn("batch", F.floor((F.col("__i") + F.col("__o")) / size).cast("long")).drop("__p", "__i", "__o")
