"""Mixing sources to target weights along a time-varying curriculum.

Each source has a share of all words; no source gives more than ``most`` times its size, and the excess goes to
the others by weight.  A source's schedule says how its weight moves over training; its integral, scaled to the target, is
the cumulative demand.  Documents of a source stand in a shuffled order that is the same in each run; the words of a
document meet the demand at certain places of that order, in the first and further passes, and the inverse of the
cumulative demand gives each pass its position in training.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ringview.llm.common import materialize, row_hash

#: Passes over a source at most, weights dealt to the sources in turn, documents of a stretch of the order.
MOST, WEIGHTS, STRETCH = 3, (1, 2, 3), 4096
#: Weight of a source relative to its mean at the start, middle and end of training: for each weight of WEIGHTS.
CURRICULUM = ((1.5, 1.0, 0.5), (1.0, 1.0, 1.0), (0.5, 1.0, 1.5))


def words(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")


def targets(sizes: DataFrame, weights: Sequence[float] = WEIGHTS, most: int = MOST) -> DataFrame:
    """(source, source_size, rank, weight, target) from (source, source_size): one row per source.

    Sources by code point, null last, take the weights in turn.  A source stops at ``most`` times its size; by the
    ratio of that cap to the weight sources reach it one after another, which gives the level for all the others.
    """
    by_name = Window.orderBy(F.col("source").isNull(), "source")
    s = sizes.withColumn("rank", F.row_number().over(by_name) - 1)
    s = s.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("rank") % len(weights) + 1).cast("int"))).withColumn("cap", F.col("source_size") * float(most))
    by_ratio = Window.orderBy(F.col("cap") / F.col("weight"), "rank")
    before, all_ = by_ratio.rowsBetween(Window.unboundedPreceding, -1), by_ratio.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    left = F.sum("source_size").over(all_).cast("double") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))
    heavy = F.sum("weight").over(all_) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    s = s.withColumn("level", left / heavy)
    open_ = F.when(F.col("cap") > F.col("level") * F.col("weight"), F.col("level"))
    s = s.withColumn("at", F.first(open_, ignorenulls=True).over(all_))
    return s.select("source", "source_size", "rank", "weight", F.least(F.col("cap"), F.coalesce(F.col("at") * F.col("weight"), F.col("cap"))).alias("target"))


def _hash(text_col: str, source_col: str) -> Column:
    return row_hash(F.col(f"`{text_col}`"), F.col(f"`{source_col}`"))


def _ordered(docs: DataFrame, text_col: str, id_col: str, source_col: str, weights, most) -> DataFrame:
    """_d, _h, source, size, source_size, rank, target, before: words of the source that stand before the document."""
    d = docs.select(F.col(f"`{id_col}`").cast("long").alias("_d"), _hash(text_col, source_col).alias("_h"), F.col(f"`{source_col}`").cast("string").alias("source"), words(F.col(f"`{text_col}`")).alias("size"))
    d = materialize(d.withColumn("place", F.xxhash64("_h", "_d")), "sizes")
    per = materialize(d.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n")), "sources")
    goal = materialize(targets(per.select("source", "source_size"), weights, most), "targets")
    # a source's order is cut to stretches by the leading bits of its places; their number follows the source's own count
    cuts = per.select("source", F.greatest(F.lit(1), F.ceil(F.col("n") / STRETCH)).cast("long").alias("cuts"))
    spread = F.shiftrightunsigned("place", 32) * F.col("cuts")
    d = d.alias("d").join(cuts.alias("c"), F.expr("d.source <=> c.source"), "left").select("d.*", "cuts").withColumn("stretch", F.shiftright(spread, 32))
    whole = d.groupBy("source", "stretch").agg(F.sum("size").alias("w"))
    run = Window.partitionBy("source").orderBy("stretch").rowsBetween(Window.unboundedPreceding, -1)
    offset = materialize(whole.withColumn("offset", F.coalesce(F.sum("w").over(run), F.lit(0))).drop("w"), "offsets")
    inside = Window.partitionBy("source", "stretch").orderBy(F.shiftrightunsigned("place", 1), "place", "_d", "_h").rowsBetween(Window.unboundedPreceding, -1)
    d = d.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0))).alias("d").join(offset.alias("o"), F.expr("d.source <=> o.source and d.stretch = o.stretch")).select("d.*", "offset")
    d = d.alias("d").join(goal.alias("g"), F.expr("d.source <=> g.source")).select("d._d", "d._h", "d.source", "d.size", "g.source_size", "g.rank", "g.target", (F.col("inside") + F.col("offset")).alias("before"))
    return d


def mix(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source", weights: Sequence[float] = WEIGHTS, most: int = MOST) -> DataFrame:
    """One row per document: _d, _h (its identity), source, size, source_size, target, taken, rank, before.

    ``taken`` counts the words that the mix takes of a document, all passes together: whole passes, and of the last,
    partial pass over the source the words before the target's end.  Null and wordless texts have size 0 and give
    nothing; a source without words has target 0; a null source is a source of its own.
    """
    d = _ordered(docs, text_col, id_col, source_col, weights, most)
    goal = F.least(F.round("target").cast("long"), F.col("source_size") * most)
    d = d.withColumn("goal", goal).withColumn("passes", F.when(F.col("source_size") > 0, F.expr("goal div source_size")).otherwise(F.lit(0).cast("long")))
    rest = F.least(F.greatest(F.col("goal") - F.col("passes") * F.col("source_size") - F.col("before"), F.lit(0)), F.col("size"))
    return d.withColumn("taken", F.col("passes") * F.col("size") + rest)


def position(demand: Column, schedule: Column) -> Column:
    """The time in [0, 1] at which a share ``demand`` of a source's words has been used, if its weight runs linearly
    through the numbers of ``schedule`` (an array, equally spaced in time)."""
    pieces = F.size(schedule) - 1
    at = lambda i: F.element_at(schedule, i + 1)
    area = F.transform(F.sequence(F.lit(0), pieces - 1), lambda i: (at(i) + at(i + 1)) / 2)
    total = F.aggregate(area, F.lit(0.0), lambda a, x: a + x)
    want = demand * total
    # the piece in which the integral reaches `want`, and the integral before it
    step = F.aggregate(
        F.sequence(F.lit(0), pieces - 1), F.struct(F.lit(0).alias("i"), F.lit(0.0).alias("done"), F.lit(False).alias("end")),
        lambda s, i: F.when(s.end | (s.done + F.element_at(area, i + 1) >= want) | (i == pieces - 1), F.struct(F.when(s.end, s.i).otherwise(i).alias("i"), s.done.alias("done"), F.lit(True).alias("end"))).otherwise(F.struct(i.alias("i"), (s.done + F.element_at(area, i + 1)).alias("done"), F.lit(False).alias("end"))),
    )
    a, slope, need = at(step.i), at(step.i + 1) - at(step.i), want - step.done
    root = 2 * need / F.nullif(a + F.sqrt(F.greatest(a * a + 2 * slope * need, F.lit(0.0))), F.lit(0.0))  # of a*x + slope*x*x/2 = need
    return F.least((step.i + F.least(F.coalesce(root, F.lit(0.0)), F.lit(1.0))) / pieces, F.lit(1.0))


def uses(m: DataFrame, most: int = MOST, curriculum: Sequence[Sequence[float]] = CURRICULUM) -> Column:
    """Of rows of ``mix``: the passes that take words of a document, in order, with pass, words and position."""
    table = F.array(*[F.array(*[F.lit(float(x)) for x in c]) for c in curriculum])
    schedule = F.element_at(table, (m["rank"] % len(curriculum) + 1).cast("int"))
    begun = lambda k: k * m["source_size"] + m["before"]
    part = lambda k: F.least(m["size"], F.greatest(m["goal"] - begun(k), F.lit(0)))
    each = F.filter(F.sequence(F.lit(0), F.least(F.lit(most - 1), m["passes"].cast("int"))), lambda k: part(k) > 0)
    return F.transform(each, lambda k: F.struct(k.alias("pass"), part(k).alias("words"), position(begun(k) / F.nullif(m["goal"], F.lit(0)), schedule).alias("position")))


def training_order(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source", weights: Sequence[float] = WEIGHTS, most: int = MOST, curriculum: Sequence[Sequence[float]] = CURRICULUM) -> DataFrame:
    """One row per document and pass: _d, _h, pass, words, position; a pass takes a document whole, or, at the target's
    end, in part."""
    m = mix(docs, text_col, id_col, source_col, weights, most)
    each = m.where("taken > 0").select("_d", "_h", "source", "size", F.explode(uses(m, most, curriculum)).alias("use"))
    return each.select("_d", "_h", "source", "use.pass", "use.words", "size", "use.position")


def training_plan(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source", weights: Sequence[float] = WEIGHTS, most: int = MOST, curriculum: Sequence[Sequence[float]] = CURRICULUM) -> DataFrame:
    """One row per document: _d, _h, size, source_size, target, taken (words of all its passes), positions (of its passes,
    in order); range-sorted by the first position, documents that no pass takes at the end."""
    m = mix(docs, text_col, id_col, source_col, weights, most)
    plan = m.select("_d", "_h", "size", "source_size", "target", uses(m, most, curriculum).alias("use"))
    taken = F.aggregate("use.words", F.lit(0).cast("long"), lambda a, x: a + x)
    plan = materialize(plan.select("_d", "_h", "size", "source_size", "target", taken.alias("taken"), F.col("use.position").alias("positions")), "plan")
    by = [F.try_element_at("positions", F.lit(1)).asc_nulls_last(), F.xxhash64("_h", "_d")]  # the many without a position are dealt out by hash
    return plan.repartitionByRange(*by).sortWithinPartitions(*by)


def mixed_documents(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", source_col: str = "source", **how) -> DataFrame:
    """The rows of ``docs`` as the mix uses them: once for each pass, range-sorted by training position.

    A pass that ends inside a document is rounded to whole documents: the row is there if at least half of its words are
    taken.  That touches one document of a source, so the words of a source differ from its target by at most half a
    document; a source of which only the first part of one document is wanted may have no row.
    """
    order = training_order(docs, text_col, id_col, source_col, **how).where("2 * words >= size")
    order = order.groupBy("_d", "_h", "pass").agg(F.collect_list("position").alias("positions"))
    order = order.groupBy("_d", "_h").agg(F.flatten(F.collect_list("positions")).alias("positions"), F.max(F.size("positions")).alias("copies"))
    # copies of a whole row: one of them stands at the positions of all
    order = materialize(order, "order")
    named = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_all"), F.col(f"`{id_col}`").cast("long").alias("_d"), _hash(text_col, source_col).alias("_h"))
    single = named.alias("l").join(order.where("copies = 1").alias("r"), F.expr("l._d <=> r._d and l._h = r._h")).select("l._all", "r.positions")
    many = named.alias("l").join(order.where("copies > 1").alias("r"), F.expr("l._d <=> r._d and l._h = r._h")).select("l._d", "l._h", "l._all", "r.positions")
    many = many.dropDuplicates(["_d", "_h"]).select("_all", "positions")
    rows = single.unionByName(many).select("_all", F.explode("positions").alias("position"))
    return rows.repartitionByRange("position").sortWithinPartitions("position").select("_all.*")
