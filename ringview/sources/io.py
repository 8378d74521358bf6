"""Scans and sinks around maintained results."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringview.operators.relation import COUNT, SIGN, KeyedRelation


_own_folder: list[str] = []


def shared_path(spark: SparkSession, tag: str) -> str:
    """A new path in the folder of spark.checkpoint.dir; where that is unset, on one machine, in a temporary one."""
    folder = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not _own_folder:
            _own_folder.append(tempfile.mkdtemp(prefix="ringview-views-"))
            atexit.register(shutil.rmtree, _own_folder[0], True)
        folder = _own_folder[0]
    return f"{folder.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def written(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written as Parquet in the shared folder and read again: a plan that starts anew."""
    path = shared_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def update_log(spark: SparkSession, path: str, schema: str, form: str = "csv", op: str = "op") -> DataFrame:
    """A log of changes in CSV or JSON: rows with an operation I or D, as a signed bag."""
    reader = spark.read.schema(f"{schema}, {op} string")
    df = reader.option("header", True).csv(path) if form == "csv" else reader.json(path)
    return df.withColumn(SIGN, F.when(F.upper(op) == "D", -1).otherwise(1)).drop(op)


def without_null_keys(df: DataFrame, keys: list[str]) -> tuple[DataFrame, int]:
    """Rows whose join keys are all there, and how many are not: a null key matches nothing."""
    bad = F.lit(False)
    for k in keys:
        bad = bad | F.col(k).isNull()
    return df.where(~bad), df.where(bad).count()


def write_result(rel: KeyedRelation, path: str, form: str = "parquet", mode: str = "errorifexists") -> None:
    df = rel.df.drop(COUNT)
    writer = df.write.mode(mode)
    writer.option("header", True).csv(path) if form == "csv" else writer.json(path) if form == "json" else writer.parquet(path)


def save_bucketed(rel: KeyedRelation, table: str, by: tuple[str, ...], buckets: int = 64) -> None:
    """A layout of a view: later joins on ``by`` need no shuffle."""
    rel.df.write.mode("overwrite").bucketBy(buckets, *by).sortBy(*by).saveAsTable(table)
