"""Streams into the engine, the replaying source, windows, SQL functions, scans and sinks."""

import json

from pyspark.sql import functions as F

from ringview.functions import sql
from ringview.functions.rings import GenCovarianceRing, IntRing
from ringview.operators.covariance import long_rows
from ringview.operators.engine import Engine
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder
from ringview.plans.viewtree import explain
from ringview.sources import datasource, io
from ringview.sources import workloads as w
from ringview.streaming.maintain import StreamMaintainer, deduplicated, sessions, support_transitions, windowed


def test_stream_equals_batch(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.repartition(4).write.parquet(str(tmp_path / "in"))
    q = NaturalJoinQuery({"ev": ("user_id", "event_type"), "lim": ("event_type", "weight")}, ("user_id",), IntRing("weight"))
    e = Engine(q, VariableOrder.parse("user_id - event_type - weight"))
    limits = spark.createDataFrame([("click", 2), ("view", 3)], "event_type string, weight long")
    e.load({"ev": events.select("user_id", "event_type").where("false"), "lim": limits})
    seen = []
    m = StreamMaintainer(e, lambda engine, n: seen.append(n))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")).select("user_id", "event_type")
    for _ in range(2):  # a restart finds nothing new
        query = m.start("ev", stream, str(tmp_path / "cp"))
        query.awaitTermination()
    assert seen == [0, 1, 2, 3]
    want = events.join(limits, "event_type").groupBy("user_id").agg(F.sum("weight").alias("v"))
    assert {tuple(r) for r in e.result().df.select("user_id", "v").collect()} == {tuple(r) for r in want.collect()}


def test_replayed_tables(spark, sf, tmp_path):
    datasource.register(spark)
    schema = "n_nationkey int, n_regionkey int, __m int"
    stream = spark.readStream.format("ringview_updates").schema(schema).options(paths=json.dumps([f"{sf}/nation.parquet"]), batch=10, turns=3).load()
    query = stream.writeStream.format("memory").queryName("replayed").option("checkpointLocation", str(tmp_path / "cp")).start()
    try:
        for _ in range(4):
            query.processAllAvailable()
        assert spark.table("replayed").where("__m = 1").count() == 25
    finally:
        query.stop()


def test_state_and_windows(spark, sf, tmp_path):
    rows = spark.createDataFrame([(1, 1), (1, 1), (1, -1), (2, 1), (2, -1)], "k long, __m int")
    rows.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(rows.schema).parquet(str(tmp_path / "in"))
    query = support_transitions(stream, ["k"]).writeStream.format("memory").queryName("moves").option("checkpointLocation", str(tmp_path / "cp")).outputMode("append").start()
    query.processAllAvailable()
    query.stop()
    assert [tuple(r) for r in spark.table("moves").collect()] == [(1, 1)]
    events = spark.read.parquet(f"{sf}/events.parquet")
    assert windowed(events, "ts", "1 day").count() == events.count() and windowed(events, "ts", "2 days", "1 day").count() == 2 * events.count()
    assert sessions(events, "ts", "1 hour", ["user_id"]).agg(F.sum("n")).first()[0] == events.count()
    assert deduplicated(spark.readStream.schema(events.schema).parquet(f"{sf}"), ["event_id"], "ts", "1 hour").isStreaming


def test_sql_functions(spark, sf):
    sql.register(spark)
    line = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_quantity", "l_extendedprice", "l_returnflag", "l_linestatus")
    line.createOrReplaceTempView("lines")
    udaf = spark.sql("select cov_agg(l_quantity, l_extendedprice) from lines").first()[0]
    fast = line.agg(*sql.covariance_columns("l_quantity", "l_extendedprice")).first()
    assert udaf[0] == fast["cnt"] and abs(udaf[4] / fast["q_l_extendedprice_l_quantity"] - 1) < 1e-9 if "q_l_extendedprice_l_quantity" in fast else True
    assert spark.sql("select ring_sum(x) from values (array(1D, 2D)), (array(3D, 4D)) t(x)").first()[0] == [4, 6]
    from ringview.plans.viewtree import build_tree

    text = explain(build_tree(NaturalJoinQuery(w.TOY.relations), w.TOY.variable_order))
    assert spark.sql(f"select * from explain_tree('{text}')").count() == len(text.split("\n")) - 1
    one = NaturalJoinQuery({"lines": ("f", "s")}, (), GenCovarianceRing((), ("f", "s")))
    e = Engine(one, VariableOrder.path(["f", "s"]))
    flags = line.select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"))
    e.load({"lines": flags})
    diagonal = "not (x = y and x <> '')"
    assert {tuple(r) for r in sql.grouping_covariance(flags, ["f", "s"]).collect()} == {tuple(r) for r in long_rows(e.result()).where(diagonal).collect()}


def test_logs_and_results(spark, tmp_path):
    (tmp_path / "log.csv").write_text("a,op\n1,I\n2,D\n,I\n")
    log = io.update_log(spark, str(tmp_path / "log.csv"), "a long")
    assert sorted((r["a"] or 0, r["__m"]) for r in log.collect()) == [(0, 1), (1, 1), (2, -1)]
    rows, missing = io.without_null_keys(log, ["a"])
    assert rows.count() == 2 and missing == 1
    q = NaturalJoinQuery({"r": ("a",)}, ("a",))
    e = Engine(q, VariableOrder.path(["a"]))
    e.load({"r": rows})
    for form in ("csv", "json", "parquet"):
        io.write_result(e.result(), str(tmp_path / form), form)
    assert spark.read.parquet(str(tmp_path / "parquet")).count() == 2
