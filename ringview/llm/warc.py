"""Content-addressed WARC archive.

An archive is two Parquet tables in one folder: ``payloads`` holds the bytes of each distinct payload once, under its
SHA-256, and ``headers`` the exact header block of each record.  Original records come back by joining the two.  Of
records with equal payloads of at least ``least`` bytes the one with the smallest id is a response and the others are
revisits; smaller payloads are stored once as well, but each of their records stays a response.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ringview.llm.common import materialize, row_hash, table_path

LEAST = 100
_EOL = "\r\n"


def _header(date: str) -> Column:
    """Header block of a record as it stands in a WARC file, with the empty line that ends it."""
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit(_EOL))
    record = lambda d, n: F.concat(F.lit("<urn:record:"), F.coalesce(d.cast("string"), F.lit("none")), F.lit(":"), n.cast("string"), F.lit(">"))
    uri = F.regexp_replace(F.coalesce("url", F.lit("")), r"[\r\n]+", "%0A")
    revisit = F.col("record_type") == "revisit"
    optional = lambda name, value: F.when(value.isNotNull(), line(name, value)).otherwise(F.lit(""))
    return F.concat(
        F.lit(f"WARC/1.1{_EOL}"), line("WARC-Type", F.col("record_type")), line("WARC-Record-ID", record(F.col("_d"), F.col("_n"))),
        line("WARC-Date", F.lit(date)), F.when(F.col("url").isNotNull(), line("WARC-Target-URI", uri)).otherwise(F.lit("")), line("WARC-Payload-Digest", F.concat(F.lit("sha256:"), F.col("digest"))),
        F.when(revisit, line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"))).otherwise(F.lit("")),
        optional("WARC-Refers-To", F.when(revisit, record(F.col("first._d"), F.col("first._n")))),
        line("Content-Type", F.lit("text/html; charset=utf-8")), line("Content-Length", F.when(revisit, F.lit("0")).otherwise(F.col("size").cast("string"))), F.lit(_EOL),
    )


def write_archive(pages: DataFrame, path: str, payload_col: str = "html", id_col: str = "page_id", url_col: str | None = "url", least: int = LEAST, date: str = "1970-01-01T00:00:00Z") -> None:
    """Write the records of ``pages`` to the folder ``path``.

    A null payload is empty; a null URL leaves its line out, and line breaks in one are escaped.  Null ids come last
    when the response is chosen; of repeated rows one is it.  The two reads of ``pages`` must give the same rows.
    """
    url = F.col(f"`{url_col}`").cast("string") if url_col else F.lit(None).cast("string")
    payload = F.coalesce(F.col(f"`{payload_col}`").cast("string"), F.lit(""))
    page = pages.select(F.col(f"`{id_col}`").cast("long").alias("_d"), row_hash(url, payload).alias("_h"), url.alias("url"), F.encode(payload, "utf-8").alias("payload"))
    light = page.select("_d", "_h", "url", F.sha2("payload", 256).alias("digest"), F.length("payload").cast("long").alias("size"), F.xxhash64("payload").alias("second"))
    light = materialize(light.withColumn("_n", F.monotonically_increasing_id()), "records")
    first = F.min(F.struct(F.col("_d").isNull().alias("x"), "_d", "_n", "_h"))
    same = (F.min("second") == F.max("second")) & (F.min("size") == F.max("size"))
    group = light.groupBy("digest").agg(first.alias("first"), F.count("*").alias("records"), same.alias("same"))
    group = materialize(group.withColumn("records", F.when(F.col("same"), F.col("records")).otherwise(F.raise_error(F.lit("equal digests of different payloads")))), "digests")
    wanted = group.select(F.col("first._d").alias("_d"), F.col("first._h").alias("_h"), "digest")
    store = page.select("_d", "_h", "payload").alias("p").join(wanted.alias("w"), F.expr("p._d <=> w._d and p._h = w._h")).select("w.digest", "p.payload")
    repeated = materialize(light.groupBy("_d", "_h").count().where("count > 1"), "repeated")
    if not repeated.isEmpty():  # copies of whole rows: one of them gives the payload
        store = store.dropDuplicates(["digest"])
    store.write.parquet(f"{path}/payloads")
    record = light.join(group.where("records > 1"), "digest", "left")
    revisit = (F.col("size") >= least) & (F.col("first._n") != F.col("_n"))
    record = record.select("*", F.when(F.coalesce(revisit, F.lit(False)), "revisit").otherwise("response").alias("record_type"))
    record.select("digest", F.encode(_header(date), "utf-8").alias("header"), F.col("_n").alias("position")).write.parquet(f"{path}/headers")


def _field(name: str) -> Column:
    """Value of a header field; lines end with CR LF only, whatever else a URL may hold."""
    return F.regexp_extract(F.decode("header", "utf-8"), rf"\r\n{name}: ([^\r\n]*)", 1)


def read_headers(spark: SparkSession, path: str) -> DataFrame:
    """Records by their headers: record_id, page_id, record_type, url, digest, refers_to, length and the header itself."""
    ident = F.regexp_extract(_field("WARC-Record-ID"), "<urn:record:([^:]*):", 1)
    target = F.regexp_extract(_field("WARC-Refers-To"), "<urn:record:([^:]*):", 1)
    url = _field("WARC-Target-URI")
    number = lambda c: c.try_cast("long")
    return spark.read.parquet(f"{path}/headers").select(
        _field("WARC-Record-ID").alias("record_id"), number(ident).alias("page_id"), _field("WARC-Type").alias("record_type"), F.when(F.contains(F.decode("header", "utf-8"), F.lit(f"{_EOL}WARC-Target-URI: ")), url).alias("url"),
        F.regexp_extract(_field("WARC-Payload-Digest"), "sha256:([0-9a-f]{64})", 1).alias("digest"), number(target).alias("refers_to"), _field("Content-Length").cast("long").alias("length"), "header", "position",
    )


def verified_payloads(spark: SparkSession, path: str) -> DataFrame:
    """(digest, size) of the stored payloads, each read back and hashed again; a stored payload that is not what its name says is an error."""
    p = spark.read.parquet(f"{path}/payloads")
    good = F.sha2("payload", 256) == F.col("digest")
    return p.select(F.when(good, F.col("digest")).otherwise(F.raise_error(F.lit("a stored payload has another digest"))).alias("digest"), F.length("payload").cast("long").alias("size"))


def read_records(spark: SparkSession, path: str) -> DataFrame:
    """One row per record, read back: page_id, payload_bytes, payload_digest, record_type, refers_to."""
    size = materialize(verified_payloads(spark, path), "sizes")
    return read_headers(spark, path).join(size, "digest").select("page_id", F.col("size").alias("payload_bytes"), F.col("digest").alias("payload_digest"), "record_type", "refers_to")


def reconstruct(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, position, record, payload): whole WARC records as in a file, and the full payload of each, revisits too."""
    h = read_headers(spark, path)
    p = spark.read.parquet(f"{path}/payloads")
    block = F.when(F.col("record_type") == "response", F.col("payload")).otherwise(F.lit(b""))
    return h.join(p, "digest").select("page_id", "position", F.concat("header", block, F.lit(b"\r\n\r\n")).alias("record"), "payload")
