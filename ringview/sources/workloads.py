"""The experiment workloads on the given tables: relations, variable orders, update scripts, and the SQL of their relations."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringview.functions.rings import Ring
from ringview.plans.query import FD, NaturalJoinQuery
from ringview.plans.varorder import VariableOrder
from ringview.sources.updates import deletes, inserts

#: Column by which the update script picks rows of the fact relation.
KEY = "__key"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def whole(c: str, factor: int = 1) -> F.Column:  # type: ignore[name-defined]
    return F.round(F.col(c) * factor).cast("long")


@dataclass(frozen=True)
class Workload:
    """``fact`` is loaded in part (key mod 10 below 7), gets the rest as inserts, loses the keys that are 3 mod 10, and
    regains those that are 3 mod 20; ``second`` is loaded in part and completed.  ``sql`` defines the final relations."""

    relations: dict[str, tuple[str, ...]]
    order: str
    build: Callable[[SparkSession, str], dict[str, DataFrame]]
    sql: str
    fact: str
    second: str | None = None
    fds: tuple[FD, ...] = ()
    static: frozenset[str] = frozenset()
    features: tuple[str, ...] = ()
    categories: tuple[str, ...] = ()

    def query(self, ring: Ring, free: tuple[str, ...] = (), static: bool = False) -> NaturalJoinQuery:
        return NaturalJoinQuery(self.relations, free, ring, self.fds, self.static if static else frozenset())

    @property
    def variable_order(self) -> VariableOrder:
        return VariableOrder.parse(self.order)

    def _key(self, r: str, db: dict[str, DataFrame]) -> F.Column:  # type: ignore[name-defined]
        return F.col(KEY) if KEY in db[r].columns else F.col(self.relations[r][0])

    def initial(self, db: dict[str, DataFrame]) -> dict[str, DataFrame]:
        out = {}
        for r, df in db.items():
            if r in (self.fact, self.second):
                df = df.where(F.pmod(self._key(r, db), F.lit(10)) < 7)
            out[r] = df.select(*self.relations[r])
        return out

    def updates(self, db: dict[str, DataFrame]) -> Iterator[tuple[str, DataFrame]]:
        f, key = db[self.fact], self._key(self.fact, db)
        late = f.where(F.pmod(key, F.lit(10)) >= 7)
        gone, back = f.where(F.pmod(key, F.lit(10)) == 3), f.where(F.pmod(key, F.lit(20)) == 3)
        cut = lambda df: df.select(*self.relations[self.fact])
        yield self.fact, inserts(cut(late))
        if self.second:
            s = db[self.second].where(F.pmod(self._key(self.second, db), F.lit(10)) >= 7)
            yield self.second, inserts(s.select(*self.relations[self.second]))
        yield self.fact, deletes(cut(gone)).unionByName(inserts(cut(back)))

    def final(self, db: dict[str, DataFrame]) -> dict[str, DataFrame]:
        key = self._key(self.fact, db)
        kept = db[self.fact].where((F.pmod(key, F.lit(10)) != 3) | (F.pmod(key, F.lit(20)) == 3))
        return {r: (kept if r == self.fact else df).select(*self.relations[r]) for r, df in db.items()}

    @property
    def joined_sql(self) -> str:
        return " NATURAL JOIN ".join(self.relations)


def _final_sql(key: str) -> str:
    return f"({key} % 10 <> 3 OR {key} % 20 = 3)"


def _toy(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    frame = lambda rows, names: spark.createDataFrame(rows, ", ".join(f"{n} long" for n in names.split()))
    return {
        "r": frame([(1, 1), (1, 2), (2, 3), (3, 4)], "a b"),
        "s": frame([(1, 1, 1), (1, 1, 2), (1, 2, 3), (2, 2, 4)], "a c e"),
        "t": frame([(1, 1), (2, 2), (2, 3), (3, 4)], "c d"),
    }


TOY_SQL = """WITH r(a, b) AS (VALUES (1, 1), (1, 2), (2, 3), (3, 4)), s(a, c, e) AS (VALUES (1, 1, 1), (1, 1, 2), (1, 2, 3), (2, 2, 4)),
t(c, d) AS (VALUES (1, 1), (2, 2), (2, 3), (3, 4))"""

TOY = Workload({"r": ("a", "b"), "s": ("a", "c", "e"), "t": ("c", "d")}, "a - {b, c - {d, e}}", _toy, TOY_SQL, "t")


def _line(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(
        F.col("l_orderkey").alias("orderkey"), F.col("l_partkey").alias("partkey"), F.col("l_suppkey").alias("suppkey"), F.to_date("l_shipdate").alias("day"),
        whole("l_quantity").alias("quantity"), whole("l_extendedprice").alias("price"), whole("l_discount", 100).alias("disc"), whole("l_tax", 100).alias("tax"), F.col("l_returnflag").alias("flag"),
    )


_LINE_SQL = """SELECT l_orderkey AS orderkey, l_partkey AS partkey, l_suppkey AS suppkey, CAST(l_shipdate AS DATE) AS day, CAST(ROUND(l_quantity) AS BIGINT) AS quantity,
CAST(ROUND(l_extendedprice) AS BIGINT) AS price, CAST(ROUND(l_discount * 100) AS BIGINT) AS disc, CAST(ROUND(l_tax * 100) AS BIGINT) AS tax, l_returnflag AS flag FROM lineitem"""


def _parts(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("partkey"), F.col("p_size").cast("long").alias("size"), whole("p_retailprice").alias("retail"), F.col("p_brand").alias("brand"), F.col("p_type").alias("ptype"))


_PARTS_SQL = "SELECT p_partkey AS partkey, CAST(p_size AS BIGINT) AS size, CAST(ROUND(p_retailprice) AS BIGINT) AS retail, p_brand AS brand, p_type AS ptype FROM part"


def _suppliers(spark, sf_dir):
    return table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("suppkey"), F.col("s_nationkey").cast("long").alias("nationkey"), whole("s_acctbal").alias("acctbal"))


_SUPP_SQL = "SELECT s_suppkey AS suppkey, CAST(s_nationkey AS BIGINT) AS nationkey, CAST(ROUND(s_acctbal) AS BIGINT) AS acctbal FROM supplier"


def _retail(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    line = _line(spark, sf_dir)
    return {
        "inv": line.select("suppkey", "day", "partkey", "quantity", "price", "disc", "tax", "flag", F.col("orderkey").alias(KEY)), "it": _parts(spark, sf_dir),
        "wx": line.groupBy("suppkey", "day").agg(F.count("*").alias("n_lines")), "loc": _suppliers(spark, sf_dir),
        "cen": table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("nationkey"), F.col("n_regionkey").cast("long").alias("regionkey")),
    }


RETAIL = Workload(
    {"inv": ("suppkey", "day", "partkey", "quantity", "price", "disc", "tax", "flag"), "it": ("partkey", "size", "retail", "brand", "ptype"), "wx": ("suppkey", "day", "n_lines"), "loc": ("suppkey", "nationkey", "acctbal"), "cen": ("nationkey", "regionkey")},
    "suppkey - {day - {partkey - {quantity - price - disc - tax - flag, size - retail - brand - ptype}, n_lines}, nationkey - {acctbal, regionkey}}", _retail,
    f"""WITH line AS ({_LINE_SQL}), inv AS (SELECT suppkey, day, partkey, quantity, price, disc, tax, flag FROM line WHERE {_final_sql("orderkey")}), it AS ({_PARTS_SQL}),
wx AS (SELECT suppkey, day, COUNT(*) AS n_lines FROM line GROUP BY suppkey, day), loc AS ({_SUPP_SQL}), cen AS (SELECT CAST(n_nationkey AS BIGINT) AS nationkey, CAST(n_regionkey AS BIGINT) AS regionkey FROM nation)""",
    "inv", "it", (FD.parse("suppkey -> nationkey"),), frozenset({"it"}), ("quantity", "price", "disc", "tax", "size", "retail", "n_lines", "acctbal"), ("flag", "brand", "ptype", "regionkey"),
)


def _snow(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    line = _line(spark, sf_dir)
    return {
        "line": line.select("orderkey", "partkey", "suppkey", "quantity", F.col("orderkey").alias(KEY)), "prt": _parts(spark, sf_dir).select("partkey", "size", "brand"),
        "sup": _suppliers(spark, sf_dir).select("suppkey", F.col("nationkey").alias("s_nation")), "ord": table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("orderkey"), F.col("o_custkey").alias("custkey"), F.col("o_orderstatus").alias("status")),
        "cust": table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("custkey"), F.col("c_nationkey").cast("long").alias("nationkey"), F.col("c_mktsegment").alias("segment")),
        "nat": table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("nationkey"), F.col("n_regionkey").cast("long").alias("regionkey")), "reg": table(spark, sf_dir, "region").select(F.col("r_regionkey").cast("long").alias("regionkey")),
    }


SNOW = Workload(
    {"line": ("orderkey", "partkey", "suppkey", "quantity"), "prt": ("partkey", "size", "brand"), "sup": ("suppkey", "s_nation"), "ord": ("orderkey", "custkey", "status"), "cust": ("custkey", "nationkey", "segment"), "nat": ("nationkey", "regionkey"), "reg": ("regionkey",)},
    "regionkey - nationkey - custkey - {orderkey - {suppkey - {partkey - {quantity, size - brand}, s_nation}, status}, segment}", _snow,
    f"""WITH l0 AS ({_LINE_SQL}), line AS (SELECT orderkey, partkey, suppkey, quantity FROM l0 WHERE {_final_sql("orderkey")}), prt AS (SELECT partkey, size, brand FROM ({_PARTS_SQL})), sup AS (SELECT suppkey, nationkey AS s_nation FROM ({_SUPP_SQL})),
ord AS (SELECT o_orderkey AS orderkey, o_custkey AS custkey, o_orderstatus AS status FROM orders), cust AS (SELECT c_custkey AS custkey, CAST(c_nationkey AS BIGINT) AS nationkey, c_mktsegment AS segment FROM customer),
nat AS (SELECT CAST(n_nationkey AS BIGINT) AS nationkey, CAST(n_regionkey AS BIGINT) AS regionkey FROM nation), reg AS (SELECT CAST(r_regionkey AS BIGINT) AS regionkey FROM region)""",
    "line", "ord", (FD.parse("orderkey -> custkey"), FD.parse("custkey -> nationkey"), FD.parse("nationkey -> regionkey")), frozenset({"prt", "sup"}), ("quantity", "size"), ("brand", "segment", "status"),
)


def _sales(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    line = _line(spark, sf_dir)
    order = table(spark, sf_dir, "orders").select(F.to_date("o_orderdate").alias("day"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"))
    return {
        "sales": line.select("day", "suppkey", "partkey", "quantity", "price", F.col("orderkey").alias(KEY)), "stores": _suppliers(spark, sf_dir), "items": _parts(spark, sf_dir).select("partkey", "size", "ptype"),
        "trans": line.groupBy("day", "suppkey").agg(F.count("*").alias("n_lines")), "holi": order.groupBy("day").agg(F.count("*").alias("n_orders")), "oil": order.where("status = 'F'").groupBy("day").agg(F.min("priority").alias("first_priority")),
    }


SALES = Workload(
    {"sales": ("day", "suppkey", "partkey", "quantity", "price"), "stores": ("suppkey", "nationkey", "acctbal"), "items": ("partkey", "size", "ptype"), "trans": ("day", "suppkey", "n_lines"), "holi": ("day", "n_orders"), "oil": ("day", "first_priority")},
    "day - {suppkey - {partkey - {quantity - price, size - ptype}, n_lines, nationkey - acctbal}, n_orders, first_priority}", _sales,
    f"""WITH line AS ({_LINE_SQL}), sales AS (SELECT day, suppkey, partkey, quantity, price FROM line WHERE {_final_sql("orderkey")}), stores AS ({_SUPP_SQL}), items AS (SELECT partkey, size, ptype FROM ({_PARTS_SQL})),
trans AS (SELECT day, suppkey, COUNT(*) AS n_lines FROM line GROUP BY day, suppkey), holi AS (SELECT CAST(o_orderdate AS DATE) AS day, COUNT(*) AS n_orders FROM orders GROUP BY 1),
oil AS (SELECT CAST(o_orderdate AS DATE) AS day, MIN(o_orderpriority) AS first_priority FROM orders WHERE o_orderstatus = 'F' GROUP BY 1)""",
    "sales", "items", (), frozenset({"stores", "items"}), ("quantity", "price", "size", "n_lines", "n_orders"), ("ptype", "first_priority"),
)

_EVENT_TYPES = ("click", "view", "purchase", "signup", "error")


def _star(n: int) -> Callable[[SparkSession, str], dict[str, DataFrame]]:
    def build(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
        ev = table(spark, sf_dir, "events")
        out = {t: ev.where(F.col("event_type") == t).select("user_id", whole("value").alias(f"{t}_value"), F.hour("ts").cast("long").alias(f"{t}_hour"), F.col("event_id").alias(KEY)) for t in _EVENT_TYPES[:n]}
        out["profile"] = ev.groupBy("user_id").agg(F.countDistinct(F.to_date("ts")).alias("active_days"), F.count("*").alias("n_events"))
        return out

    return build


def _star_sql(n: int) -> str:
    parts = [f"{t} AS (SELECT user_id, CAST(ROUND(value) AS BIGINT) AS {t}_value, CAST(hour(ts) AS BIGINT) AS {t}_hour FROM events WHERE event_type = '{t}'{' AND ' + _final_sql('event_id') if t == 'click' else ''})" for t in _EVENT_TYPES[:n]]
    return "WITH " + ", ".join([*parts, "profile AS (SELECT user_id, COUNT(DISTINCT CAST(ts AS DATE)) AS active_days, COUNT(*) AS n_events FROM events GROUP BY user_id)"])


def star(n: int = 3) -> Workload:
    """Star over the first ``n`` event types and the user's profile."""
    types = _EVENT_TYPES[:n]
    return Workload(
        {t: ("user_id", f"{t}_value", f"{t}_hour") for t in types} | {"profile": ("user_id", "active_days", "n_events")},
        f"user_id - {{{', '.join(f'{t}_value - {t}_hour' for t in types)}, active_days - n_events}}", _star(n), _star_sql(n), "click", "view", features=(*(f"{t}_value" for t in types), "active_days"), categories=tuple(f"{t}_hour" for t in types),
    )


def _nation_star(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {
        "customers": table(spark, sf_dir, "customer").select(F.col("c_nationkey").cast("long").alias("nationkey"), F.col("c_custkey").alias("custkey")), "suppliers": table(spark, sf_dir, "supplier").select(F.col("s_nationkey").cast("long").alias("nationkey"), F.col("s_suppkey").alias("suppkey")),
        "nations": table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("nationkey"), F.col("n_regionkey").cast("long").alias("regionkey")),
    }


NATIONS = Workload(
    {"customers": ("nationkey", "custkey"), "suppliers": ("nationkey", "suppkey"), "nations": ("nationkey", "regionkey")}, "nationkey - {custkey, suppkey, regionkey}", _nation_star,
    f"""WITH customers AS (SELECT CAST(c_nationkey AS BIGINT) AS nationkey, c_custkey AS custkey FROM customer WHERE (c_nationkey % 10 <> 3 OR c_nationkey % 20 = 3)), suppliers AS (SELECT CAST(s_nationkey AS BIGINT) AS nationkey, s_suppkey AS suppkey FROM supplier),
nations AS (SELECT CAST(n_nationkey AS BIGINT) AS nationkey, CAST(n_regionkey AS BIGINT) AS regionkey FROM nation)""",
    "customers", "suppliers",
)


def _cycle(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    s = _snow(spark, sf_dir)
    return {"line": s["line"].select("orderkey", "suppkey", "quantity", KEY), "ord": s["ord"].select("orderkey", "custkey"), "cust": s["cust"].select("custkey", "nationkey"), "sup": s["sup"].select("suppkey", F.col("s_nation").alias("nationkey"))}


CYCLE = Workload(
    {"line": ("orderkey", "suppkey", "quantity"), "ord": ("orderkey", "custkey"), "cust": ("custkey", "nationkey"), "sup": ("suppkey", "nationkey")}, "nationkey - custkey - suppkey - orderkey - quantity", _cycle,
    f"""WITH l0 AS ({_LINE_SQL}), line AS (SELECT orderkey, suppkey, quantity FROM l0 WHERE {_final_sql("orderkey")}), ord AS (SELECT o_orderkey AS orderkey, o_custkey AS custkey FROM orders),
cust AS (SELECT c_custkey AS custkey, CAST(c_nationkey AS BIGINT) AS nationkey FROM customer), sup AS (SELECT suppkey, nationkey FROM ({_SUPP_SQL}))""",
    "line", "cust",
)


def part_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst): parts on neighbouring lines of an order."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    nxt = line.select("l_orderkey", (F.col("l_linenumber") - 1).alias("l_linenumber"), F.col("l_partkey").alias("dst"))
    return line.join(nxt, ["l_orderkey", "l_linenumber"]).where("l_partkey <> dst").select(F.col("l_partkey").alias("src"), "dst").distinct()


GRAPH_SQL = """e AS (SELECT DISTINCT x.l_partkey AS src, y.l_partkey AS dst FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND y.l_linenumber = x.l_linenumber + 1 WHERE x.l_partkey <> y.l_partkey)"""


def user_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst): users whose events follow each other.  Events are numbered by range, so no task sorts them all."""
    from pyspark.sql.window import Window

    ev = table(spark, sf_dir, "events").select("ts", "event_id", "user_id").withColumn("day", F.to_date("ts"))
    by = Window.partitionBy("day").orderBy("ts", "event_id")
    inside = ev.withColumn("dst", F.lead("user_id").over(by))
    first = ev.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("head"))
    nxt = first.withColumn("after", F.lead("head").over(Window.orderBy("day"))).select("day", "after")  # a row for each day
    return inside.join(F.broadcast(nxt), "day").select(F.col("user_id").alias("src"), F.coalesce("dst", "after").alias("dst")).where("dst is not null and src <> dst").distinct()


def edges_as(graph: DataFrame, a: str, b: str) -> DataFrame:
    return graph.select(F.col("src").alias(a), F.col("dst").alias(b), F.col("src").alias(KEY))


def triangle(graph: Callable[[SparkSession, str], DataFrame], graph_sql: str = GRAPH_SQL) -> Workload:
    def build(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
        g = graph(spark, sf_dir)
        return {"r": edges_as(g, "a", "b"), "s": edges_as(g, "b", "c"), "t": edges_as(g, "c", "a")}

    sql = f"WITH {graph_sql}, r AS (SELECT src AS a, dst AS b FROM e WHERE {_final_sql('src')}), s AS (SELECT src AS b, dst AS c FROM e), t AS (SELECT src AS c, dst AS a FROM e)"
    return Workload({"r": ("a", "b"), "s": ("b", "c"), "t": ("c", "a")}, "a - b - c", build, sql, "r", "s")


def loop4(graph: Callable[[SparkSession, str], DataFrame] = part_graph, graph_sql: str = GRAPH_SQL) -> Workload:
    """Four edges in a loop and a chord."""

    def build(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
        g = graph(spark, sf_dir)
        return {"ab": edges_as(g, "a", "b"), "bc": edges_as(g, "b", "c"), "cd": edges_as(g, "c", "d"), "da": edges_as(g, "d", "a"), "ac": edges_as(g, "a", "c")}

    sql = f"WITH {graph_sql}, ab AS (SELECT src AS a, dst AS b FROM e), bc AS (SELECT src AS b, dst AS c FROM e), cd AS (SELECT src AS c, dst AS d FROM e), da AS (SELECT src AS d, dst AS a FROM e), ac AS (SELECT src AS a, dst AS c FROM e WHERE {_final_sql('src')})"
    return Workload({"ab": ("a", "b"), "bc": ("b", "c"), "cd": ("c", "d"), "da": ("d", "a"), "ac": ("a", "c")}, "a - c - {b, d}", build, sql, "ac", "ab")


def path(k: int, graph: Callable[[SparkSession, str], DataFrame] = part_graph, graph_sql: str = GRAPH_SQL) -> Workload:
    """Paths over k edges."""

    def build(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
        g = graph(spark, sf_dir)
        return {f"e{i}": edges_as(g, f"a{i}", f"a{i + 1}") for i in range(1, k + 1)}

    names = [f"e{i} AS (SELECT src AS a{i}, dst AS a{i + 1} FROM e{' WHERE ' + _final_sql('src') if i == 1 else ''})" for i in range(1, k + 1)]
    order = " - ".join(["a1", f"a{k + 1}", *(f"a{i}" for i in range(k, 1, -1))])
    return Workload({f"e{i}": (f"a{i}", f"a{i + 1}") for i in range(1, k + 1)}, order, build, f"WITH {graph_sql}, {', '.join(names)}", "e1", "e2" if k > 1 else None)


def documents(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    d = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", F.col("n_chars").cast("long").alias("n_chars"), F.col("doc_id").alias(KEY))
    return {"doc": d, "lab": table(spark, sf_dir, "labels").select("doc_id", F.col("quality").cast("string").alias("quality"), F.col("toxic").cast("string").alias("toxic"))}


DOCUMENTS = Workload(
    {"doc": ("doc_id", "lang", "source", "n_chars"), "lab": ("doc_id", "quality", "toxic")}, "doc_id - {lang - source - n_chars, quality - toxic}", documents,
    f"WITH doc AS (SELECT doc_id, lang, source, CAST(n_chars AS BIGINT) AS n_chars FROM documents WHERE {_final_sql('doc_id')}), lab AS (SELECT doc_id, CAST(quality AS VARCHAR) AS quality, CAST(toxic AS VARCHAR) AS toxic FROM labels)",
    "doc", "lab", features=("n_chars",), categories=("lang", "source", "quality", "toxic"),
)
