"""The queries of this subpackage: each applies an operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringview.llm import exact_dedup, langid, maxscore, mixing, quality, sentencepiece, simhash, substring_dedup, url_filter, warc
from ringview.llm.common import table_path


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exact_dedup.find_copies(_table(spark, sf_dir, "documents"))
    return found.select(F.col("_d").alias("doc_id"), "keep_id", "group_size", "kept", "text_sha256")


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece.encode(_table(spark, sf_dir, "documents"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(_table(spark, sf_dir, "documents"))
    return found.select(F.col("_d").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "links")


def captures(pages: DataFrame) -> DataFrame:
    """Pages with the fetch date that the tables do not have: a day of 2024 by id."""
    return pages.select("page_id", "url", F.date_add(F.lit("2024-01-01").cast("date"), F.pmod(F.col("page_id") * 37, F.lit(366)).cast("int")).alias("fetched"))


def url_list(pages: DataFrame) -> DataFrame:
    """A dated list over the pages' own hosts: by its smallest page each host has up to three entries, and two domains
    and one section are listed for a part of the year."""
    first = pages.select(url_filter.host(F.col("url")).alias("pattern"), "page_id").where("pattern <> ''").groupBy("pattern").agg(F.min("page_id").alias("n"))
    start = F.date_add(F.lit("2024-01-01").cast("date"), F.pmod(F.col("n") * 7, F.lit(300)).cast("int"))
    entry = lambda shift, action: F.struct(F.date_add(start, shift).alias("day"), F.lit(action).alias("action"))
    each = F.when(F.col("n") % 2 == 0, F.array(entry(0, "add"), entry(40, "remove"), entry(70, "add"))).otherwise(F.array(entry(0, "add")))
    hosts = first.where("n % 3 = 0").select(F.lit("domain").alias("kind"), "pattern", F.explode(each).alias("e")).select("kind", "pattern", "e.day", "e.action")
    paths = first.where("n % 3 = 1").select(F.lit("path").alias("kind"), F.concat("pattern", F.lit("/en")).alias("pattern"), start.alias("day"), F.lit("add").alias("action"))
    return hosts.unionByName(paths)


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _table(spark, sf_dir, "pages")
    return url_filter.filter_captures(captures(pages), url_list(pages))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    model = quality.fit(docs, _table(spark, sf_dir, "labels"))
    scored = quality.score(docs, model)
    return scored.select(F.col("_d").alias("doc_id"), quality.held_out("_d").alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = table_path(spark, "archive")
    warc.write_archive(_table(spark, sf_dir, "pages"), path)
    return warc.read_records(spark, path)


def op7_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maxscore.top_k(_table(spark, sf_dir, "embeddings"))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = mixing.training_plan(_table(spark, sf_dir, "documents"))
    return plan.select(F.col("_d").alias("doc_id"), "size", "source_size", "target", "taken", "positions")


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    found = langid.predict(docs, langid.fit(docs))
    return found.select(F.col("_d").alias("doc_id"), langid.held_out("_d").alias("held_out"), "lang_pred", "score", "ambiguous")


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substring_dedup.remove_repeats(_table(spark, sf_dir, "documents"), digest_only=True)
    return found.select(F.col("_d").alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256", (F.col("n_removed") > 0).alias("repeated"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_exact_dedup, op2_sentencepiece, op3_simhash, op4_url_filter, op5_quality, op6_warc, op7_top_k, op8_mixing, op9_language, op10_substring_dedup, pipeline)
}

_FOLDED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_HOST = r"regexp_replace(lower(regexp_extract(coalesce(url, ''), '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]*)', 1)), '\.$', '')"

ORACLES: dict[str, str] = {
    "op1_exact_dedup": f"""
        with t as (select doc_id, {_FOLDED} as folded from documents)
        select doc_id, max(doc_id) over g as keep_id, count(*) over g as group_size,
               row_number() over (partition by folded order by doc_id desc) = 1 as kept, sha256(folded) as text_sha256
        from t window g as (partition by folded)""",
    "op4_url_filter": f"""
        with c as (select page_id, {_HOST} as host,
                          lower(regexp_extract(coalesce(url, ''), '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*/([^/?#]*)', 1)) as segment,
                          date '2024-01-01' + cast(page_id * 37 % 366 as int) as fetched from pages),
        h as (select host as pattern, min(page_id) as n from c where host <> '' group by host),
        e as (select 'domain' as kind, pattern, date '2024-01-01' + cast(n * 7 % 300 as int) as since,
                     case when n % 2 = 0 then date '2024-01-01' + cast(n * 7 % 300 as int) + 40 else date '9999-12-31' end as until from h where n % 3 = 0
              union all select 'domain', pattern, date '2024-01-01' + cast(n * 7 % 300 as int) + 70, date '9999-12-31' from h where n % 3 = 0 and n % 2 = 0
              union all select 'path', pattern || '/en', date '2024-01-01' + cast(n * 7 % 300 as int), date '9999-12-31' from h where n % 3 = 1),
        labels_of as (select distinct host, string_split(host, '.') as l from c where host <> ''),
        tried as (select host, array_to_string(l[i:], '.') as pattern from (select host, l, unnest(range(1, len(l) + 1)) as i from labels_of)),
        m as (select c.page_id, e.kind, e.pattern, e.since from c join tried t on c.host = t.host join e on e.kind = 'domain' and e.pattern = t.pattern and c.fetched >= e.since and c.fetched < e.until
              union all select c.page_id, e.kind, e.pattern, e.since from c join e on e.kind = 'path' and e.pattern = c.host || '/' || c.segment and c.fetched >= e.since and c.fetched < e.until),
        v as (select page_id, count(*) as n_lists, min(since) as since, (list(pattern order by kind, pattern))[1] as pattern from m group by page_id)
        select c.page_id, c.host, c.fetched, v.page_id is not null as blocked, coalesce(v.n_lists, 0) as n_lists, v.since, v.pattern
        from c left join v on c.page_id = v.page_id""",
    "op6_warc": """
        with p as (select page_id, encode(coalesce(html, '')) as payload from pages),
        d as (select page_id, octet_length(payload) as payload_bytes, sha256(payload) as payload_digest from p),
        r as (select *, min(page_id) over (partition by payload_digest) as first_id from d)
        select page_id, cast(payload_bytes as bigint) as payload_bytes, payload_digest,
               case when payload_bytes >= 100 and page_id <> first_id then 'revisit' else 'response' end as record_type,
               case when payload_bytes >= 100 and page_id <> first_id then first_id end as refers_to
        from r""",
    "op7_top_k": """
        with v as (select vec_id, list_transform(embedding, lambda x: floor(64 * cast(x as double))) as v from embeddings
                   where vec_id is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
        s as (select q.vec_id as query_id, c.vec_id, cast(list_inner_product(q.v, c.v) as bigint) as score from v q join v c on q.vec_id % 20 = 0 and q.vec_id <> c.vec_id),
        r as (select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s)
        select query_id, cast(rank as int) as rank, vec_id, score from r where rank <= 20""",
}
