"""URL filter by temporal list join, with DataFrame functions only.

List entries are dated: an ``add`` opens, a ``remove`` ends the validity of a pattern, which is a domain (with its
subdomains) or a host with the first segment of a path.  Entries become validity intervals; each capture is judged
by the entries that are valid at its own fetch date.  Captures are judged once for each distinct (host, segment, date),
and intervals are dealt to calendar periods, so neither a common host nor a long history makes pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ringview.llm.common import keyed, materialize

#: Days of a period, the unit in which intervals and captures meet.
PERIOD = 32


def host(url: Column) -> Column:
    """Lower-cased host of a URL, without user, port and trailing dot; empty if there is none."""
    return F.regexp_replace(F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]*)", 1)), r"\.$", "")


def segment(url: Column) -> Column:
    """First segment of the path; empty if there is none."""
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*/([^/?#]*)", 1)


def validity(entries: DataFrame) -> DataFrame:
    """(kind, pattern, since, until): days in [since, until) on which a pattern is listed.  ``entries``: kind ('domain'
    or 'path'), pattern, day (date), action ('add', anything else removes).  Rows with a null are passed over; of
    several entries of a day the removal counts; an addition while listed changes nothing."""
    day = entries.select("kind", F.lower("pattern").alias("pattern"), F.col("day").cast("date").alias("day"), (F.lower("action") == "add").cast("int").alias("on")).na.drop()
    day = day.groupBy("kind", "pattern", "day").agg(F.min("on").alias("on"))
    order = Window.partitionBy("kind", "pattern").orderBy("day")
    turn = day.withColumn("was", F.coalesce(F.lag("on").over(order), F.lit(0))).where("on <> was")
    return turn.withColumn("until", F.lead("day").over(order)).where("on = 1").select("kind", "pattern", F.col("day").alias("since"), F.coalesce("until", F.lit("9999-12-31").cast("date")).alias("until"))


def patterns(h: Column, s: Column) -> Column:
    """All (kind, pattern) that may list a host and segment: all suffixes of the host, and host/segment."""
    labels = F.split(h, r"\.")
    suffix = lambda n: F.array_join(F.slice(labels, -n, n), ".")
    domains = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda n: F.struct(F.lit("domain").alias("kind"), suffix(n).alias("pattern")))
    path = F.array(F.struct(F.lit("path").alias("kind"), F.concat(h, F.lit("/"), F.lower(s)).alias("pattern")))
    return F.concat(domains, path)


def filter_captures(captures: DataFrame, entries: DataFrame, id_col: str = "page_id", url_col: str = "url", fetched_col: str = "fetched", period: int = PERIOD) -> DataFrame:
    """One row per capture: id, host, fetched, blocked, n_lists (patterns valid at the fetch date), since (the earliest
    day from which one of them has been valid), pattern (the first of them by kind and text).

    A capture without host or date is not blocked.  Repeated captures are judged alike, each with its own row.
    """
    c = captures.select(F.col(f"`{id_col}`").cast("long").alias("_d"), host(F.col(f"`{url_col}`")).alias("host"), segment(F.col(f"`{url_col}`")).alias("segment"), F.col(f"`{fetched_col}`").cast("date").alias("fetched"))
    place = materialize(c.where("host <> '' and fetched is not null").select("host", "segment", "fetched").distinct(), "places")
    reach = place.agg(F.min("fetched").alias("a"), F.max("fetched").alias("b")).first()
    number = lambda day: F.floor(F.datediff(day, F.lit("1970-01-01").cast("date")) / period).cast("int")
    first, last = (F.lit(x).cast("date") for x in (reach["a"], reach["b"]))
    valid = validity(entries).where((F.col("since") <= last) & (F.col("until") > first))
    valid = valid.withColumn("period", F.explode(F.sequence(number(F.greatest("since", first)), number(F.least(F.date_sub("until", 1), last)))))
    tried = place.select("*", number(F.col("fetched")).alias("period"), F.explode(patterns(F.col("host"), F.col("segment"))).alias("p")).select("host", "segment", "fetched", "period", "p.kind", "p.pattern")
    met = tried.join(valid, ["kind", "pattern", "period"]).where("fetched >= since and fetched < until")
    verdict = met.groupBy("host", "segment", "fetched").agg(F.count("*").alias("n_lists"), F.min("since").alias("since"), F.min(F.struct("kind", "pattern")).alias("p"))
    verdict = materialize(verdict, "verdicts")
    out = c.join(verdict, ["host", "segment", "fetched"], "left")
    return out.select(F.col("_d").alias(id_col), "host", "fetched", F.col("n_lists").isNotNull().alias("blocked"), F.coalesce("n_lists", F.lit(0)).cast("long").alias("n_lists"), "since", F.col("p.pattern").alias("pattern"))


ENTRY_SCHEMA = T.StructType([T.StructField("kind", T.StringType()), T.StructField("pattern", T.StringType()), T.StructField("day", T.DateType()), T.StructField("action", T.StringType())])
