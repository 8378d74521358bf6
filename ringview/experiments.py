"""Further experiment workloads as queries: streams of batches, result modes and encodings on all joins, long paths, ranks
of updates, dense graphs, binned mutual information, regression on each join."""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringview.functions.rings import BigIntRing, ComplexRing, CovarianceRing, IntRing, JointCovarianceRing, MatrixRing, NatSemiring, NumberRing
from ringview.operators import baselines
from ringview.operators.conjunctive import Factorized, listing_query
from ringview.operators.covariance import Moments, long_rows
from ringview.operators.engine import Engine, choose_order
from ringview.operators.factored import rank_r
from ringview.operators.matrix_chain import MatrixChain
from ringview.operators.metrics import enum_run, run_stream
from ringview.operators.mutual_info import Discretizer, InformationStream, mutual_information
from ringview.operators.regression import OnlineRegression, loss, solve
from ringview.operators.relation import AT, KeyedRelation, indicator, join, marginalize, negate, union
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder, free_top_order
from ringview.queries import _MAT_SQL, _MI, _MIXED, ORACLES, QUERIES, _cov_sql, _list_sql, _long_sql, _matrices, _mi_sql, _number, _product, _rows, _sum_sql, by_baseline, maintained, query
from ringview.sources import workloads as w
from ringview.sources.io import shared_path
from ringview.sources.store import ParquetStore
from ringview.sources.updates import Batch, deletes, inserts, numbered, round_robin, turn, turns
from ringview.sources.workloads import Workload

__all__ = ["ORACLES", "QUERIES"]  # those of ringview.queries, and these


# --- streams of batches -----------------------------------------------------------------------------------------------------
def batch_table(df: DataFrame, order: Sequence[str], size: int) -> tuple[DataFrame, int]:
    """The rows along ``order`` in batches of ``size``, written once so that a batch reads its own rows only; how many there are."""
    path = shared_path(df.sparkSession, "stream")
    rows = numbered(df, order, size)
    rows.write.partitionBy("batch").parquet(path)
    whole = df.sparkSession.read.schema(rows.schema).parquet(path)
    n = whole.agg(F.max("batch")).first()[0]
    return whole, 0 if n is None else n + 1


def batches(df: DataFrame, order: Sequence[str], size: int, keep: Sequence[str]) -> list[DataFrame]:
    whole, n = batch_table(df, order, size)
    return [whole.where(F.col("batch") == i).select(*keep) for i in range(n)]


def stream(work: Workload, db: dict[str, DataFrame], size: int) -> Iterator[Batch]:
    """Everything as inserts, round robin over all relations, each along the variable order; then the fact relation loses
    and partly regains rows as in the update script."""
    along = list(work.variable_order.variables)
    parts = {r: [inserts(b) for b in batches(df.select(*work.relations[r]), [v for v in along if v in work.relations[r]], size, work.relations[r])] for r, df in db.items()}
    yield from round_robin(parts)
    yield list(work.updates(db))[-1]


def waiting(work: Workload, db: dict[str, DataFrame], size: int) -> tuple[dict[str, DataFrame], list[str]]:
    """The batches of ``stream``, those of a relation in one table with their numbers, and the relation of each number."""
    along = list(work.variable_order.variables)
    tables = {r: batch_table(df.select(*work.relations[r]), [v for v in along if v in work.relations[r]], size) for r, df in db.items()}
    count = {r: n for r, (_, n) in tables.items()}
    out = {r: inserts(df.select(*work.relations[r], turn(count, r, F.col("batch")))) for r, (df, _) in tables.items()}
    order = turns(count)
    relation, delta = list(work.updates(db))[-1]
    out[relation] = out[relation].unionByName(delta.withColumn(AT, F.lit(len(order)).cast("long")))
    return out, [*order, relation]


#: Batches of a stream that are taken in the same jobs if they wait.
TOGETHER = 256


def apply_waiting(e: Engine, tables: dict[str, DataFrame], order: list[str], name: str = "all", together: int = TOGETHER) -> None:
    for low in range(0, len(order), together):
        part = order[low : low + together]
        e.apply_together({r: tables[r].where(F.col(AT).between(low, low + len(part) - 1)) for r in dict.fromkeys(part)}, (name, low + len(part) - 1))


def streamed_waiting(spark: SparkSession, sf_dir: str, work: Workload, q: NaturalJoinQuery, size: int) -> Engine:
    """As ``streamed``, where the stream is there before it is read, so that batches wait."""
    db = work.build(spark, sf_dir)
    e = Engine(q, work.variable_order, store=ParquetStore(spark, shared_path(spark, "views"), q.ring, buckets=1))
    e.load({r: df.select(*work.relations[r]).limit(0) for r, df in db.items()})
    apply_waiting(e, *waiting(work, db, size))
    return e


def streamed(spark: SparkSession, sf_dir: str, work: Workload, q: NaturalJoinQuery, size: int, **how) -> Engine:
    """From empty tables, batch by batch, into views on disk."""
    db = work.build(spark, sf_dir)
    store = ParquetStore(spark, shared_path(spark, "views"), q.ring, buckets=1)
    e = Engine(q, work.variable_order, store=store, **how)
    e.load({r: df.select(*work.relations[r]).limit(0) for r, df in db.items()})
    for i, (relation, delta) in enumerate(stream(work, db, size)):
        e.apply(relation, delta, ("all", i))
    return e


_STAR2 = w.star(2)
for _size in (1_000, 10_000, 100_000):
    query(f"stream_star_batch_{_size}", _cov_sql(_STAR2, _STAR2.features))(lambda s, d, n=_size: _rows(streamed(s, d, _STAR2, _STAR2.query(CovarianceRing(_STAR2.features, NumberRing("long"))), n).result()))
query("stream_nations", _sum_sql(w.NATIONS, "custkey"))(lambda s, d: _rows(streamed_waiting(s, d, w.NATIONS, w.NATIONS.query(IntRing("custkey")), 1_000).result()))
query("stream_retail_batch_100000", _sum_sql(w.RETAIL, "quantity"))(lambda s, d: _rows(streamed(s, d, w.RETAIL, w.RETAIL.query(IntRing("quantity")), 100_000).result()))


@query("stream_restarted", _sum_sql(w.NATIONS, "custkey"))
def _(spark, sf_dir):
    """Stopped after some batches, opened again from the files; batches that come twice count once."""
    work, q = w.NATIONS, w.NATIONS.query(IntRing("custkey"))
    db, path = work.build(spark, sf_dir), shared_path(spark, "views")
    tables, order = waiting(work, db, 1_000)
    first = Engine(q, work.variable_order, store=ParquetStore(spark, path, q.ring, buckets=2, prune=0))
    first.load({r: df.select(*work.relations[r]).limit(0) for r, df in db.items()})
    for i, relation in enumerate(order[:3]):
        first.apply(relation, tables[relation].where(F.col(AT) == i).drop(AT), ("all", i))
    again = Engine(q, work.variable_order, store=ParquetStore(spark, path, q.ring, buckets=2, prune=0))
    if not again.resumed:
        raise RuntimeError("the store lacks views")
    apply_waiting(again, tables, order)
    again.store.vacuum()
    return _rows(again.result())


# --- payload layouts: categories as rows with continuous columns, multiplicities above the payloads -----------------------------------------------
for _name in ("retail", "star", "documents"):
    _work, _cont, _cat = _MIXED[f"mixed_{_name}"]
    query(f"covariance_hybrid_{_name}", _long_sql(_work, _cont, _cat))(lambda s, d, work=_work, cont=_cont, cat=_cat: long_rows(maintained(work, s, d, work.query(JointCovarianceRing(cont, cat))).result()))

_GROUPED = {"retail": (w.RETAIL, ("quantity", "price", "size"), ("nationkey", "suppkey", "day")), "star": (w.star(2), ("click_value", "view_value"), ("user_id", "click_hour")), "sales": (w.SALES, w.SALES.features[:2], ("day", "suppkey"))}
for _name, (_work, _f, _free) in _GROUPED.items():

    @query(f"covariance_count_only_above_{_name}", _cov_sql(_work, _f, _free))
    def _(spark, sf_dir, work=_work, f=_f, free=_free):
        """Covariances by several free variables: the views that only tell which groups there are carry no matrices."""
        q = work.query(CovarianceRing(f, NumberRing("long")), free)
        return _rows(maintained(work, spark, sf_dir, q, free_top_order(q), free_top=True, count_only_above=True).result())


# --- modes, encodings and orders on all joins -----------------------------------------------------------------------------
_FULL: dict[str, tuple[Workload, tuple[str, ...]]] = {
    "star": (w.star(2), ("user_id", "click_value", "view_value")), "retail": (w.RETAIL, ("nationkey", "suppkey", "day", "partkey", "quantity")),
    "sales": (w.SALES, ("day", "suppkey", "partkey", "quantity")), "snow": (w.SNOW, ("regionkey", "nationkey", "custkey", "orderkey", "quantity")),
}
for _name, (_work, _free) in _FULL.items():
    for _eager in (True, False):
        for _fact in (True, False):
            query(f"mode_{'eager' if _eager else 'lazy'}_{'fact' if _fact else 'list'}_{_name}", _list_sql(_work, _free))(
                lambda s, d, work=_work, free=_free, a=_eager, b=_fact: _rows(by_baseline(work, s, d, lambda db: baselines.ResultMode(work.query(IntRing(), free), db, a, b)).result()).select(*free, "v")
            )


def changing(work: Workload, db: dict[str, DataFrame]) -> tuple[dict[str, DataFrame], list[Batch]]:
    """Initial relations, static ones whole, and the changes of the others."""
    first = work.initial(db)
    first |= {r: db[r].select(*work.relations[r]) for r in work.static}
    return first, [(r, delta) for r, delta in work.updates(db) if r not in work.static]


for _name, _work in {"retail": w.RETAIL, "snow": w.SNOW, "sales": w.SALES, "star": w.star(2)}.items():
    _vars = tuple(dict.fromkeys(v for s in _work.relations.values() for v in s))

    @query(f"full_join_static_{_name}", _list_sql(_work, _vars))
    def _(spark, sf_dir, work=_work, names=_vars):
        """The whole join with static relations and dependencies: the canonical order where the query has one."""
        q = work.query(IntRing(), names, static=True)
        first, changes = changing(work, work.build(spark, sf_dir))
        e = Engine(q, choose_order(q, True), free_top=True)
        e.load(first)
        for r, delta in changes:
            e.apply(r, delta)
        return _rows(e.result()).select(*names, "v")


_ENCODED = {"star": (w.star(2), ("user_id", "click_value", "view_value")), "retail": (w.RETAIL, ("suppkey", "day", "partkey", "quantity"))}
for _name, (_work, _free) in _ENCODED.items():
    query(f"encoding_keys_{_name}", _list_sql(_work, _free))(lambda s, d, work=_work, free=_free: _rows(maintained(work, s, d, work.query(IntRing(), free)).result()).select(*free, "v"))

    @query(f"encoding_listing_payload_{_name}", _list_sql(_work, _free))
    def _(spark, sf_dir, work=_work, free=_free):
        e = maintained(work, spark, sf_dir, listing_query(work.query(IntRing(), free)))
        return e.result().df.select(*[F.col(f"p_{x}").cast("date" if x == "day" else "long").alias(x) for x in free], "v")

    @query(f"encoding_factorized_payload_{_name}", _list_sql(_work, _free))
    def _(spark, sf_dir, work=_work, free=_free):
        """Maintained: each variable's view takes its part of a change."""
        db = work.build(spark, sf_dir)
        store = ParquetStore(spark, shared_path(spark, "views"), IntRing(), buckets=1)  # long orders: plans start anew at each view
        f = Factorized(work.query(IntRing(), free), work.variable_order, work.initial(db), store)
        for r, delta in work.updates(db):
            f.apply(r, delta)
        return f.expand()


# --- paths --------------------------------------------------------------------------------------------------------------------
def _path_total_sql(k: int) -> str:
    """Counts of paths, edge by edge from the last to the first."""
    steps = [f"p{k} AS (SELECT src AS node, CAST(COUNT(*) AS HUGEINT) AS n FROM e GROUP BY src)"]
    for i in range(k - 1, 0, -1):
        where = " WHERE " + w._final_sql("src") if i == 1 else ""
        steps.append(f"p{i} AS (SELECT e.src AS node, SUM(p{i + 1}.n) AS n FROM e JOIN p{i + 1} ON e.dst = p{i + 1}.node{where} GROUP BY e.src)")
    return f"WITH {w.GRAPH_SQL}, {', '.join(steps)} SELECT CAST(SUM(n) AS VARCHAR) AS v FROM p1"


for _k in (6, 10, 15, 20):
    _p = w.path(_k)
    query(f"path_{_k}_total", _path_total_sql(_k))(
        lambda s, d, p=_p, k=_k: _rows(maintained(p, s, d, p.query(BigIntRing()), VariableOrder.path([f"a{i}" for i in range(1, k + 2)])).result()).select(F.col("v").cast("string").alias("v"))
    )


# --- dense graphs, copies of one relation, moved relations ----------------------------------------------------------------------
USERS_SQL = """e0 AS (SELECT user_id AS src, LEAD(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events), e AS (SELECT DISTINCT src, dst FROM e0 WHERE dst IS NOT NULL AND src <> dst)"""
SUPPLIERS_SQL = """e0 AS (SELECT l_suppkey AS src, LEAD(l_suppkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem), e AS (SELECT DISTINCT src, dst FROM e0 WHERE dst IS NOT NULL AND src <> dst)"""


def supplier_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst): suppliers on neighbouring lines of an order."""
    from pyspark.sql.window import Window

    by = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    line = w.table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return line.select(F.col("l_suppkey").alias("src"), F.lead("l_suppkey").over(by).alias("dst")).where("dst is not null and src <> dst").distinct()


_DENSE = {"users": w.triangle(w.user_graph, USERS_SQL), "suppliers": w.triangle(supplier_graph, SUPPLIERS_SQL)}
for _name, _work in _DENSE.items():
    query(f"triangle_{_name}", _sum_sql(_work, None))(lambda s, d, work=_work: _rows(maintained(work, s, d, work.query(IntRing()), indicators=True).result()))
query("triangle_users_covariance", _cov_sql(_DENSE["users"], "abc"))(lambda s, d: _rows(maintained(_DENSE["users"], s, d, _DENSE["users"].query(CovarianceRing(tuple("abc"), NumberRing("long"))), indicators=True).result()))
query("triangle_users_first_order", _sum_sql(_DENSE["users"], None))(lambda s, d: _rows(by_baseline(_DENSE["users"], s, d, lambda db: baselines.FirstOrder(_DENSE["users"].query(IntRing()), db)).result()))
query("triangle_by_difference", _sum_sql(w.triangle(w.part_graph), None))(lambda s, d: _rows(maintained(w.triangle(w.part_graph), s, d, w.triangle(w.part_graph).query(IntRing()), indicators=True, by_difference=True).result()))
query("triangle_moved", _sum_sql(w.triangle(w.part_graph), None))(lambda s, d: _rows(maintained(w.triangle(w.part_graph), s, d, w.triangle(w.part_graph).query(IntRing()), place={"r": "c"}).result()))


@query("triangle_one_symbol", f"WITH {w.GRAPH_SQL}, f AS (SELECT * FROM e WHERE {w._final_sql('src')}) SELECT CAST(COUNT(*) AS BIGINT) AS v FROM f x JOIN f y ON x.dst = y.src JOIN f z ON y.dst = z.src AND z.dst = x.src")
def _(spark, sf_dir):
    """One edge relation in three places: a change goes to one after another."""
    g = w.part_graph(spark, sf_dir)
    q = NaturalJoinQuery({"r": ("a", "b"), "s": ("b", "c"), "t": ("c", "a")}, (), IntRing())
    e = Engine(q, VariableOrder.parse("a - b - c"), same={"edge": ["r", "s", "t"]}, indicators=True)
    key = F.pmod("src", F.lit(10))
    e.load({r: g.where(key < 7).toDF(*q.relations[r]) for r in q.relations})
    for delta in (inserts(g.where(key >= 7)), deletes(g.where(key == 3)).unionByName(inserts(g.where(F.pmod("src", F.lit(20)) == 3)))):
        e.apply("edge", delta)
    return _number(e.result())


@query("sum_of_two_trees", "SELECT CAST((SELECT SUM(c_custkey) FROM customer) * (SELECT COUNT(*) FROM part) AS BIGINT) AS v")
def _(spark, sf_dir):
    """Relations that share nothing: the results of two trees are multiplied."""
    q = NaturalJoinQuery({"customers": ("custkey", "nationkey"), "parts": ("partkey", "size")}, (), IntRing("custkey"))
    c = w.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("custkey"), F.col("c_nationkey").cast("long").alias("nationkey"))
    p = w.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("partkey"), F.col("p_size").cast("long").alias("size"))
    e = Engine(q, VariableOrder.parse("custkey - nationkey; partkey - size"))
    e.load({"customers": c.where("custkey % 10 < 7"), "parts": p.where("partkey % 10 < 7")})
    e.apply("customers", inserts(c.where("custkey % 10 >= 7")))
    e.apply("parts", inserts(p.where("partkey % 10 >= 7")))
    return _rows(e.result())


# --- matrices -------------------------------------------------------------------------------------------------------------------
def _rank_sql(r: int) -> str:
    change = f"(SELECT SUM(((t.k * j0) % 7 - 3) * ((t.k * j) % 5 - 2)) FROM range(1, {r + 1}) t(k))"
    return _MAT_SQL.replace("a2 AS (SELECT i, j, v FROM a1 WHERE i < 64)", f"a2 AS (SELECT i, j, CAST(v + {change} AS BIGINT) AS v FROM (SELECT i, j, v, i AS j0 FROM a1 WHERE i < 64))")


for _r in (4, 16, 64):

    @query(f"matrix_rank_{_r}_update", _rank_sql(_r))
    def _(spark, sf_dir, r=_r):
        """All terms of the change as one pair of relations with a term number."""
        mats, dims = _matrices(spark, sf_dir)
        chain = MatrixChain(mats, dims, updatable=[1])
        i = np.arange(64)
        u, v = (np.stack([(k * i) % m - c for k in range(1, r + 1)], axis=1) for m, c in ((7, 3), (5, 2)))
        chain.update(1, rank_r(spark, u, v, "x2", "x3", together=True))
        return _product(chain.product())


@query("matrix_row_column_entry", _MAT_SQL.replace("a2 AS (SELECT i, j, v FROM a1 WHERE i < 64)", "a2 AS (SELECT i, j, v + CASE WHEN i = 5 THEN j ELSE 0 END + CASE WHEN j = 7 THEN 2 * i ELSE 0 END + CASE WHEN i = 9 AND j = 11 THEN 1000 ELSE 0 END AS v FROM a1 WHERE i < 64)"))
def _(spark, sf_dir):
    mats, dims = _matrices(spark, sf_dir)
    chain = MatrixChain(mats, dims, updatable=[1])
    n = spark.range(64)
    chain.update_row(1, 5, n.select("id", F.col("id").alias("v")))
    chain.update_column(1, 7, n.select("id", (2 * F.col("id")).alias("v")))
    chain.update_entry(1, 9, 11, 1000)
    return _product(chain.product())


# --- mutual information with bins -------------------------------------------------------------------------------------------------
def binned(work: Workload, columns: dict[str, tuple[str, str]], bins: int = 100) -> Workload:
    """Continuous columns become bins over their range in the whole relation.  ``columns``: variable to (relation, the
    SQL table that has the whole column)."""

    def build(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
        db = dict(work.build(spark, sf_dir))
        for v, (r, _) in columns.items():
            db[r] = db[r].withColumn(v, Discretizer(bins).fit(db[r], v).expr(v))
        return db

    ranges = ", ".join(f"range_{v} AS (SELECT CAST(MIN({v}) AS DOUBLE) AS a, CAST(MAX({v}) AS DOUBLE) AS b FROM {t})" for v, (_, t) in columns.items())
    bin_ = lambda v: f"CAST(GREATEST(0, LEAST(FLOOR((CAST({v} AS DOUBLE) - (SELECT a FROM range_{v})) * {bins} / (SELECT CASE WHEN b = a THEN 1 ELSE b - a END FROM range_{v})), {bins - 1})) AS INT) AS {v}"
    return replace(work, build=build, sql=f"{work.sql}, {ranges}, joined AS (SELECT * REPLACE ({', '.join(map(bin_, columns))}) FROM {work.joined_sql})")


_BINNED = {
    "retail": (binned(w.RETAIL, {"price": ("inv", "line"), "acctbal": ("loc", "loc"), "retail": ("it", "it")}), ("price", "acctbal", "retail", "flag", "brand")),
    "sales": (binned(w.SALES, {"price": ("sales", "line"), "n_orders": ("holi", "holi")}), ("price", "n_orders", "ptype")),
    "star": (binned(w.star(2), {"view_value": ("view", "view"), "n_events": ("profile", "profile")}), ("view_value", "n_events", "click_hour")),
    "documents": (binned(w.DOCUMENTS, {"n_chars": ("doc", "(SELECT n_chars FROM documents)")}), ("n_chars", "lang", "quality", "toxic")),
}


def _binned_mi(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    work, cat = _BINNED[name]
    return mutual_information(long_rows(maintained(work, spark, sf_dir, work.query(JointCovarianceRing((), cat))).result()))


def _binned_sql(name: str) -> str:
    work, cat = _BINNED[name]
    return _mi_sql(work, cat).replace(f"j AS (SELECT * FROM {work.joined_sql})", "j AS (SELECT * FROM joined)")


for _name in _BINNED:
    query(f"mutual_information_binned_{_name}", _binned_sql(_name))(lambda s, d, name=_name: _binned_mi(s, d, name).withColumn("mi", F.round("mi", 6)))


def tree_sql(mi: str) -> str:
    """(parent, child, mi) of the largest spanning tree, grown from the smallest name: an edge is in it if its ends are not
    connected by better ones."""
    return f"""WITH RECURSIVE mi AS MATERIALIZED ({mi}), ranked AS (SELECT x, y, mi, row_number() OVER (ORDER BY mi DESC, x, y) AS r FROM mi),
sides AS (SELECT x, y, r FROM ranked UNION ALL SELECT y, x, r FROM ranked),
reach(r, node) AS (SELECT r, x FROM ranked UNION SELECT reach.r, b.y FROM reach JOIN sides b ON b.x = reach.node AND b.r < reach.r),
edge AS (SELECT x, y, mi FROM ranked e WHERE NOT EXISTS (SELECT 1 FROM reach WHERE reach.r = e.r AND reach.node = e.y)),
step AS (SELECT x AS a, y AS b, mi FROM edge UNION ALL SELECT y, x, mi FROM edge),
grown(parent, child, mi) AS (SELECT a, b, mi FROM step WHERE a = (SELECT MIN(x) FROM mi) UNION SELECT s.a, s.b, s.mi FROM grown g JOIN step s ON s.a = g.child AND s.b <> g.parent)
SELECT parent, child, mi FROM grown"""


ORACLES["dependency_tree"] = tree_sql(_mi_sql(*_MI["retail"]))


@query("dependency_tree_per_batch", tree_sql(_binned_sql("documents")))
def _(spark, sf_dir):
    """A tree after every batch; the last one is returned."""
    work, cat = _BINNED["documents"]
    db, s = work.build(spark, sf_dir), InformationStream()
    e = Engine(work.query(JointCovarianceRing((), cat)), work.variable_order)
    e.load(work.initial(db))
    s.after_batch(long_rows(e.result()))
    for r, delta in work.updates(db):
        e.apply(r, delta)
        s.after_batch(long_rows(e.result()))
    return spark.createDataFrame([(p, c, round(float(x), 6)) for p, c, x in s.trees[-1]], "parent string, child string, mi double")


# --- regression on each join -------------------------------------------------------------------------------------------------------
_LEARN = {"retail": (w.RETAIL, "quantity", ("price", "acctbal")), "sales": (w.SALES, "quantity", ("size", "n_lines")), "star": (w.star(3), "purchase_value", ("click_value", "active_days")), "snow": (w.SNOW, "quantity", ("size",))}


def _r2_sql(work: Workload, y: str, x: Sequence[str]) -> str:
    c = lambda a, b: f"corr({a}, {b})"
    r2 = f"({c(y, x[0])} ** 2 + {c(y, x[1])} ** 2 - 2 * {c(y, x[0])} * {c(y, x[1])} * {c(*x)}) / (1 - {c(*x)} ** 2)" if len(x) == 2 else f"{c(y, x[0])} ** 2"
    return f"{work.sql} SELECT ROUND({r2}, 6) AS r2, CAST(1 AS BOOLEAN) AS same_from_both_starts, CAST(1 AS BOOLEAN) AS warm_is_shorter FROM {work.joined_sql}"


for _name, (_work, _y, _x) in _LEARN.items():

    @query(f"regression_{_name}", _r2_sql(_work, _y, _x))
    def _(spark, sf_dir, work=_work, y=_y, x=_x):
        """Trained after every batch from the last parameters and from zero; the fit of the last model."""
        db = work.build(spark, sf_dir)
        e = Engine(work.query(CovarianceRing((*x, y), NumberRing("long"))), work.variable_order)
        e.load(work.initial(db))
        runs = [OnlineRegression(y, x, mode) for mode in ("warm", "scratch")]
        m = Moments.of(e.result())
        for r in runs:
            r.after_batch(m)
        for relation, delta in work.updates(db):
            e.apply(relation, delta)
            m = Moments.of(e.result())
            for r in runs:
                r.after_batch(m)
        fit = [loss(m, r.model)["r2"] for r in runs]
        best = loss(m, solve(m, y, x))["r2"]
        return spark.createDataFrame([(round(best, 6), bool(np.allclose(fit, best, atol=1e-4)), runs[0].iterations <= runs[1].iterations)], "r2 double, same_from_both_starts boolean, warm_is_shorter boolean")


# --- rings with data of their own kind ------------------------------------------------------------------------------------------------
class _Points(ComplexRing):
    """Customers and suppliers as complex numbers: key plus i times the key modulo 7."""

    def lift(self, var, value):
        return {"re": value.cast("double"), "im": F.pmod(value, F.lit(7)).cast("double")} if var in self.lifts else self.one()


class _Shears(MatrixRing):
    """Customers shear one way, suppliers the other: the product depends on the order of factors."""

    def lift(self, var, value):
        one = self.one()
        if var == "custkey":
            one["m0_1"] = F.pmod(value, F.lit(5)).cast("double")
        elif var == "suppkey":
            one["m1_0"] = F.pmod(value, F.lit(3)).cast("double")
        return one


_JOIN = w.NATIONS.joined_sql
query("ring_complex_points", f"{w.NATIONS.sql} SELECT regionkey, CAST(SUM(custkey * suppkey - (custkey % 7) * (suppkey % 7)) AS DOUBLE) AS re, CAST(SUM(custkey * (suppkey % 7) + (custkey % 7) * suppkey) AS DOUBLE) AS im FROM {_JOIN} GROUP BY regionkey")(
    lambda s, d: _rows(maintained(w.NATIONS, s, d, w.NATIONS.query(_Points(("custkey", "suppkey")), ("regionkey",))).result())
)
query("ring_matrix_shears", f"{w.NATIONS.sql} SELECT CAST(SUM(1 + (custkey % 5) * (suppkey % 3)) AS DOUBLE) AS m0_0, CAST(SUM(custkey % 5) AS DOUBLE) AS m0_1, CAST(SUM(suppkey % 3) AS DOUBLE) AS m1_0, CAST(COUNT(*) AS DOUBLE) AS m1_1 FROM {_JOIN}")(
    lambda s, d: _rows(maintained(w.NATIONS, s, d, w.NATIONS.query(_Shears(2))).result())
)


@query("ring_natural_numbers", "SELECT CAST(n_regionkey AS BIGINT) AS regionkey, CAST(COUNT(*) AS BIGINT) AS v FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN supplier ON s_nationkey = n_nationkey GROUP BY 1")
def _(spark, sf_dir):
    """Counts without negatives: inserts only."""
    db = w.NATIONS.build(spark, sf_dir)
    e = Engine(w.NATIONS.query(NatSemiring("long"), ("regionkey",)), w.NATIONS.variable_order)
    e.load(w.NATIONS.initial(db))
    for r, delta in list(w.NATIONS.updates(db))[:2]:
        e.apply(r, delta)
    return _rows(e.result())


# --- operators on the given tables ----------------------------------------------------------------------------------------------------
def _sides(spark: SparkSession, sf_dir: str, *lifts: str) -> tuple[KeyedRelation, KeyedRelation]:
    db = w.NATIONS.build(spark, sf_dir)
    bag = lambda r, k: KeyedRelation.from_bag(db[r].select("nationkey", F.col(k).alias("key")), ("nationkey", "key"), IntRing(*lifts))
    return bag("customers", "custkey"), bag("suppliers", "suppkey")


_SIDES = "c AS (SELECT CAST(c_nationkey AS BIGINT) AS nationkey, c_custkey AS key FROM customer), s AS (SELECT CAST(s_nationkey AS BIGINT) AS nationkey, s_suppkey AS key FROM supplier)"
_by = lambda rel: marginalize(rel, ["key"])
query("relation_union", f"WITH {_SIDES} SELECT nationkey, key, CAST(COUNT(*) AS BIGINT) AS v FROM (SELECT * FROM c UNION ALL SELECT * FROM s) GROUP BY 1, 2")(lambda s, d: _rows(union(*_sides(s, d))))
query("relation_join", f"WITH {_SIDES} SELECT nationkey, CAST(x.n * y.n AS BIGINT) AS v FROM (SELECT nationkey, COUNT(*) AS n FROM c GROUP BY 1) x JOIN (SELECT nationkey, COUNT(*) AS n FROM s GROUP BY 1) y USING (nationkey)")(lambda s, d: _rows(join(*map(_by, _sides(s, d)))))
query("relation_marginalize", f"WITH {_SIDES} SELECT nationkey, CAST(SUM(key) AS BIGINT) AS v FROM (SELECT * FROM c UNION ALL SELECT * FROM s) GROUP BY 1")(lambda s, d: _rows(_by(union(*_sides(s, d, "key")))))
query("relation_negate", f"WITH {_SIDES} SELECT nationkey, CAST(-COUNT(*) AS BIGINT) AS v FROM c GROUP BY 1")(lambda s, d: _rows(negate(_by(_sides(s, d)[0]))))
query("relation_indicator", f"WITH {_SIDES} SELECT DISTINCT nationkey, CAST(1 AS BIGINT) AS v FROM c")(lambda s, d: _rows(indicator(_sides(s, d)[0], ["nationkey"])).select("nationkey", F.col("v").cast("long").alias("v")))
query("relation_slice", f"WITH {_SIDES} SELECT nationkey, key, CAST(1 AS BIGINT) AS v FROM c WHERE nationkey = 3")(lambda s, d: _sides(s, d)[0].slice(nationkey=3).select("nationkey", "key", "v"))


@query("payload_of_one_tuple", f"{w.NATIONS.sql} SELECT CAST(COUNT(*) AS BIGINT) AS v FROM {_JOIN} WHERE nationkey = 7")
def _(spark, sf_dir):
    """One entry of a result in factorized form: a lookup in each of the lowest views."""
    q = w.NATIONS.query(IntRing(), ("nationkey", "regionkey"))
    e = maintained(w.NATIONS, spark, sf_dir, q, VariableOrder.parse("nationkey - {regionkey, custkey, suppkey}"), free_top=True)
    region = w.table(spark, sf_dir, "nation").where("n_nationkey = 7").first()["n_regionkey"]
    return e.payload_of(nationkey=7, regionkey=region).agg(F.coalesce(F.sum("v"), F.lit(0)).cast("long").alias("v"))  # none is zero


@query("outer_join_of_result", f"{w.NATIONS.sql} SELECT CAST(r_regionkey AS BIGINT) AS regionkey, CAST(COALESCE(x.v, 0) AS BIGINT) AS v FROM region LEFT JOIN (SELECT regionkey, COUNT(*) AS v FROM {_JOIN} GROUP BY 1 HAVING COUNT(*) > 1000) x ON x.regionkey = r_regionkey")
def _(spark, sf_dir):
    """Outer joins and conditions stand around a maintained result."""
    found = _rows(maintained(w.NATIONS, spark, sf_dir, w.NATIONS.query(IntRing(), ("regionkey",))).result()).where("v > 1000")
    every = w.table(spark, sf_dir, "region").select(F.col("r_regionkey").cast("long").alias("regionkey"))
    return every.join(found, "regionkey", "left").select("regionkey", F.coalesce("v", F.lit(0)).cast("long").alias("v"))


# --- measures of runs (for bench.py and tests; seconds differ from run to run, so these are no queries) -----------------------------
def strategies(spark: SparkSession, sf_dir: str, work: Workload, size: int = 1_000, limit: float = 30.0) -> dict[str, dict]:
    """One sum over the same stream by view tree, first-order and recursive maintenance and by re-evaluation after every
    batch: tuples a second, by tenth of the stream, stored views, and a mark if the limit ended it."""
    db = work.build(spark, sf_dir)
    q = work.query(IntRing())
    empty = {r: df.select(*work.relations[r]).limit(0) for r, df in db.items()}
    all_ = list(stream(work, db, size))
    tree = Engine(q, work.variable_order, store=ParquetStore(spark, shared_path(spark, "views"), q.ring, buckets=1))
    tree.load(empty)
    runs: dict[str, tuple] = {"view_tree": (tree, tree.result)}
    for name, make in (("first_order", baselines.FirstOrder), ("recursive", baselines.Recursive)):
        runs[name] = (b := make(q, empty), b.result)
    runs["plain_reeval"] = (mode := baselines.ResultMode(q, empty, False, False), mode.result)
    out = {}
    for name, (engine, result) in runs.items():
        run = run_stream(all_, engine.apply, lambda result=result: result().df.collect(), limit)
        views = engine.view_count() if hasattr(engine, "view_count") else 1 + len(q.relations)
        out[name] = {"tuples_per_s": round(run.throughput, 1), "tenths": [round(x) for x in run.curve()], "views": views, "stopped": run.mark}
    return out


def enumeration_costs(spark: SparkSession, sf_dir: str, intervals: Sequence[int] = (1, 2, 4), size: int = 1_000) -> dict[str, dict[int, float]]:
    """Seconds of the four result modes with a request after every so many batches."""
    work = w.NATIONS
    db = work.build(spark, sf_dir)
    q = work.query(IntRing(), ("nationkey", "custkey", "suppkey"))
    empty = {r: df.select(*work.relations[r]).limit(0) for r, df in db.items()}
    all_ = list(stream(work, db, size))
    out: dict[str, dict[int, float]] = {}
    for eager in (True, False):
        for fact in (True, False):
            for n in intervals:
                mode = baselines.ResultMode(q, empty, eager, fact)
                out.setdefault(mode.name, {})[n] = round(enum_run(all_, mode, n)[1], 2)
    return out


def rank_costs(spark: SparkSession, sf_dir: str, ranks: Sequence[int] = (1, 8, 64)) -> dict[str, float]:
    """Seconds of a change of rank r of the middle matrix and of the same change as a dense one."""
    mats, dims = _matrices(spark, sf_dir)
    i, out = np.arange(64), {}
    for r in ranks:
        u, v = (np.stack([(k * i) % m - c for k in range(1, r + 1)], axis=1) for m, c in ((7, 3), (5, 2)))
        chain = MatrixChain(mats, dims, updatable=[1])
        chain.engine.store.force()
        t = time.perf_counter()
        chain.update(1, rank_r(spark, u, v, "x2", "x3", together=True), keep_factored=True)
        chain.engine.store.force()
        out[f"rank_{r}"] = round(time.perf_counter() - t, 2)
    return out
