"""Queries of this subpackage: ``(spark, sf_dir) -> DataFrame``, and SQL where it can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, edit_fingerprint, mixture_fit, near_dedup, quality_model, quality_rules, secret_scan, suffix_dedup, url_filter, warc_derivatives
from ._spark import table

#: Crawl day of a page and the dated list are derived from the pages themselves.
FIRST_DAY = "2024-01-01"


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _sha(column: str) -> F.Column:
    return F.sha2(F.col(column), 256)


def op1_near_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Near-duplicate groups of all documents by two-word shingles at 0.8."""
    return near_dedup.near_duplicates(table(spark, d, "documents"), shingle=2, percent=80)


def op2_quality_rules(spark: SparkSession, d: str) -> DataFrame:
    """Base metrics and adaptive verdict of all documents."""
    return quality_rules.quality_verdicts(table(spark, d, "documents")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def op3_bpe(spark: SparkSession, d: str) -> DataFrame:
    """Digests of ids and decoded text of all documents."""
    got = bpe.encode_documents(table(spark, d, "documents"), tokenizer_path())
    return got.select("doc_id", "n_tokens", _sha("ids").alias("ids_sha256"), _sha("decoded").alias("decoded_sha256"))


def op4_suffix_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Repeated 50-byte strings cut out of all documents."""
    return suffix_dedup.deduplicate(table(spark, d, "documents"), 50, texts=False).drop("kept")


def _dated_list(pages: DataFrame) -> DataFrame:
    """A log over the hosts of ``pages``: some are listed, some of these removed, some listed again."""
    hosts = pages.select(url_filter.host_of(F.col("url")).alias("value")).where("value <> ''").distinct()
    h = F.conv(F.substring(F.md5("value"), 1, 8), 16, 10).cast("long")
    day = lambda n: F.date_add(F.lit(FIRST_DAY).cast("date"), n.cast("int"))
    listed = hosts.withColumn("h", h).where("h % 3 = 0").withColumn("kind", F.when(F.col("h") % 2 == 0, "host").otherwise("domain"))
    start = F.col("h") % 200
    event = lambda action, when, on: F.when(on, F.struct(F.lit(action).alias("action"), day(when).alias("at")))
    log = F.array(
        event("add", start, F.lit(True)), event("remove", start + 60, F.col("h") % 5 < 3), event("add", start + 90, F.col("h") % 7 == 0)
    )
    return listed.select("kind", "value", F.explode(F.filter(log, lambda e: e.isNotNull())).alias("e")).select("kind", "value", "e.action", "e.at")


def op5_url_filter(spark: SparkSession, d: str) -> DataFrame:
    """All pages judged by the list as it stood on their crawl day."""
    pages = table(spark, d, "pages")
    captures = pages.select("page_id", "url", F.date_add(F.lit(FIRST_DAY).cast("date"), (F.col("page_id") % 365).cast("int")).alias("fetched"))
    got = url_filter.judge_captures(captures, _dated_list(pages))
    return got.select("page_id", "host", F.col("fetched").cast("string").alias("fetch_day"), "n_active", "first_entry", "blocked")


def op6_edit_fingerprint(spark: SparkSession, d: str) -> DataFrame:
    """Fingerprints of all documents and of their edited texts, and the near group of each document."""
    return edit_fingerprint.grouped_edits(table(spark, d, "documents"))


def _seen_labels(labels: DataFrame) -> DataFrame:
    return labels.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0)


def op7_quality_classifier(spark: SparkSession, d: str) -> DataFrame:
    """Scores of all documents, learned from the labels outside the held-out fold."""
    scored = quality_model.quality_scores(table(spark, d, "documents"), _seen_labels(table(spark, d, "labels")))
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    return scored.select("doc_id", held.alias("held_out"), "score", "predicted")


def op8_mixture(spark: SparkSession, d: str) -> DataFrame:
    """The mix of all documents at weights 3, 1, 2."""
    got = mixture_fit.mix(table(spark, d, "documents"))
    return got.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def op9_warc_derivatives(spark: SparkSession, d: str) -> DataFrame:
    """Conversion and metadata records of all pages, their bytes as a digest."""
    got = warc_derivatives.derive(warc_derivatives.responses(table(spark, d, "pages")))
    return got.select("page_id", "kind", "record_id", "refers_to", "source_digest", "block_digest", "block_bytes", _sha("record").alias("record_sha256"))


def op10_secret_scan(spark: SparkSession, d: str) -> DataFrame:
    """Secrets in all documents."""
    return secret_scan.scan(table(spark, d, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [
        op1_near_dedup, op2_quality_rules, op3_bpe, op4_suffix_dedup, op5_url_filter, op6_edit_fingerprint, op7_quality_classifier,
        op8_mixture, op9_warc_derivatives, op10_secret_scan,
    ]
    return {f.__name__: f for f in found}


def _op5_sql() -> str:
    host = r"lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)', 1))"
    return f"""
with p as (select page_id, {host} as host, date '{FIRST_DAY}' + (page_id % 365)::int as fetched from pages),
hosts as (select distinct host as value, ('0x' || substr(md5(host), 1, 8))::bigint as h from p where host <> ''),
listed as (select *, case when h % 2 = 0 then 'host' else 'domain' end as kind, date '{FIRST_DAY}' + (h % 200)::int as t from hosts where h % 3 = 0),
log as (select kind, value, 'add' as action, t as event_day from listed
  union all select kind, value, 'remove', t + 60 from listed where h % 5 < 3
  union all select kind, value, 'add', t + 90 from listed where h % 7 = 0),
spans as (select *, lead(event_day) over (partition by kind, value order by event_day, action) as until_day from log),
valid as (select kind, value, event_day as since_day, until_day from spans where action = 'add'),
hits as (select page_id, count(*) as n, min(value) as first_entry
  from p join valid v on (v.value = p.host or v.kind = 'domain' and ends_with(p.host, '.' || v.value))
    and v.since_day <= p.fetched and (v.until_day is null or p.fetched < v.until_day) group by 1)
select page_id, host, fetched::varchar as fetch_day, coalesce(n, 0)::bigint as n_active, first_entry, n is not null as blocked
from p left join hits using (page_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op5_url_filter": _op5_sql()}
