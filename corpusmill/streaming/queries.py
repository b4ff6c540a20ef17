"""Streaming forms: windows, late data, dedup, joins, and an incremental band index.

The batch drivers below replay a table as a file stream with ``availableNow``
and return the final state as a DataFrame, so a stream can be held against the
batch result.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import minhash, paragraphs, rules
from ..plans import methods as M
from ..session import scratch
from ..sources.tables import load


def _stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table's files as a stream of its own schema."""
    schema = load(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/{name}*")


def _final(df: DataFrame, mode: str) -> DataFrame:
    """Run over all that is there and return what the sink holds: Parquet in the shared folder, so no row passes the driver."""
    spark, base = df.sparkSession, f"{scratch(df.sparkSession)}/sink-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, k: int) -> None:
        # A complete result replaces the one before it; a batch that is run again replaces itself.
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={0 if mode == 'complete' else k}")

    df.sparkSession.createDataFrame([], df.schema).write.parquet(f"{base}/out/batch=-1")
    q = df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{base}/out").select(*df.columns)


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def stream_tumbling(spark, d):
    """Events per day and kind."""
    e = _events(spark, d).withWatermark("ts", "1 hour")
    got = e.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return _final(got, "complete").select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


def stream_sliding(spark, d):
    """Events in two-hour windows every hour."""
    e = _events(spark, d).withWatermark("ts", "1 hour")
    got = e.groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count("*").alias("n"))
    return _final(got, "complete").select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


def stream_session(spark, d):
    """Sessions of a user with gaps below eight hours."""
    e = _events(spark, d).withWatermark("ts", "1 hour")
    got = e.groupBy("user_id", F.session_window("ts", "8 hours")).agg(F.count("*").alias("n"))
    return _final(got, "complete").select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def stream_watermark_late(spark, d):
    """Events per day where every twentieth event arrives two arrivals late, beyond the watermark unless its day is still open.

    Arrivals hold six days each and are replayed one file at a time. In update
    mode a window is written as often as it grows; its last count is its state.
    """
    path = f"{scratch(spark)}/arrivals-{uuid.uuid4().hex}"
    e = load(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    late = F.when(F.col("event_id") % 20 == 0, 2).otherwise(0)
    e = e.withColumn("arrival", F.floor(F.datediff("ts", F.lit("2024-01-01")) / 6) + late)
    lo, hi = e.agg(F.min("arrival"), F.max("arrival")).first()
    for k in range(lo, hi + 1) if lo is not None else ():
        e.where(F.col("arrival") == k).select("event_id", "ts").coalesce(1).write.mode("append").parquet(path)  # one file is one arrival
    if lo is None:
        e.select("event_id", "ts").write.parquet(path)
    stream = spark.readStream.schema("event_id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(path)
    got = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return _final(got, "update").groupBy(F.date_format("window.start", "yyyy-MM-dd").alias("day")).agg(F.max("n").alias("n"))


def stream_dedup(spark, d):
    """First event of each user and kind and day, by keys within the watermark."""
    e = _events(spark, d).withColumn("day", F.date_format("ts", "yyyy-MM-dd")).withWatermark("ts", "2 days")
    got = e.dropDuplicatesWithinWatermark(["user_id", "event_type", "day"]).select("user_id", "event_type", "day")
    return _final(got, "append")


def stream_static_join(spark, d):
    """Streamed documents with static labels."""
    docs = _stream(spark, d, "documents").select("doc_id", "lang")
    return _final(docs.join(load(spark, d, "labels"), "doc_id").select("doc_id", "lang", "quality"), "append")


def stream_stream_join(spark, d):
    """Clicks with purchases of the same user within the hour after."""
    e = _events(spark, d)
    c = e.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("click_id"), F.col("ts").alias("ct")).withWatermark("ct", "1 hour")
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("pt")).withWatermark("pt", "1 hour")
    got = c.join(p, F.expr("u = user_id and pt >= ct and pt <= ct + interval 1 hour"))
    return _final(got.select("click_id", "purchase_id"), "append")


def stream_funnel(spark, d):
    """Running counts of documents that pass the length rule, by language."""
    docs = _stream(spark, d, "documents").select("lang", (F.col("n_chars") >= 300).alias("keep"))
    return _final(docs.groupBy("lang").agg(F.count("*").alias("docs"), F.count_if("keep").alias("kept")), "complete")


def incremental_dedup(bands: DataFrame, index: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Drop rows of a new snapshot against themselves and a band index; returns losers and the new index.

    ``index(band, key, first_id)`` holds the smallest id of every bucket seen.
    If ids rise with arrival, the losers of all snapshots together are those of
    one pass over everything.
    """
    own = bands.groupBy("band", "key").agg(F.min("doc_id").alias("first_id"))
    merged = own.unionByName(index).groupBy("band", "key").agg(F.min("first_id").alias("first_id"))
    losers = bands.join(merged, ["band", "key"]).where("doc_id <> first_id").groupBy("doc_id").agg(F.min("first_id").alias("witness"))
    return losers, merged


class BandIndex:
    """Buckets seen so far, kept as Parquet in the shared folder: every batch adds a part with the buckets it is the first to fill.

    A batch that is run again reads the parts before it and writes its own anew, so a restart changes nothing.
    """

    SCHEMA = "band int, key string, first_id long, batch int"

    def __init__(self, spark: SparkSession, path: str):
        self.path = path
        spark.createDataFrame([], "band int, key string, first_id long").write.mode("overwrite").parquet(f"{path}/batch=-1")

    def losers(self, bands: DataFrame, batch: int) -> DataFrame:
        """``(doc_id, witness)`` of the rows of a batch that share a bucket with a smaller id; the batch's new buckets are added."""
        spark = bands.sparkSession
        bands = minhash.checkpointed(bands)
        known = spark.read.schema(self.SCHEMA).parquet(self.path).where(F.col("batch") < batch).drop("batch")
        new = bands.groupBy("band", "key").agg(F.min("doc_id").alias("first_id")).join(known, ["band", "key"], "left_anti")
        new.write.mode("overwrite").parquet(f"{self.path}/batch={batch}")
        return incremental_dedup(bands, known)[0]


def _refresh(spark: SparkSession, sf_dir: str, step: Callable[[DataFrame, int], None], base: str, arrivals: int = 4) -> None:
    """Documents arrive in ranges of rising ids; after each arrival the same stream runs on over what is new, from its checkpoint."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    size = (docs.agg(F.max("doc_id")).first()[0] or 0) // arrivals + 1
    for k in range(arrivals):
        docs.where(F.floor(F.col("doc_id") / size) == k).write.mode("append").parquet(f"{base}/in")
        stream = spark.readStream.schema(docs.schema).parquet(f"{base}/in").writeStream.foreachBatch(step)
        stream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start().awaitTermination()


def stream_incremental_lsh(spark, d):
    """Losers of every refresh against the stored band index: together those of one pass over everything."""
    base = f"{scratch(spark)}/refresh-{uuid.uuid4().hex}"
    index = BandIndex(spark, f"{base}/index")

    def step(batch: DataFrame, k: int) -> None:
        index.losers(minhash.lsh_bands(minhash.minhash_signatures(batch)), k).write.mode("overwrite").parquet(f"{base}/out/batch={k}")

    _refresh(spark, d, step, base)
    return spark.read.schema("doc_id long, witness long, batch int").parquet(f"{base}/out").drop("batch")


def stream_web_track(spark, d):
    """A refresh of the web track: language, document rules, near copies against the stored index, into a Parquet table by snapshot."""
    base = f"{scratch(spark)}/refresh-{uuid.uuid4().hex}"
    index = BandIndex(spark, f"{base}/index")

    def step(batch: DataFrame, k: int) -> None:
        told = rules.score_document_rules(batch.where("lang = 'en'").select("doc_id", "text", "source"))
        kept = told.where(~rules.any_flag(told.columns)).select("doc_id", "text", paragraphs.snapshot(F.col("source")).alias("snapshot")).persist()
        gone = index.losers(minhash.lsh_bands(minhash.minhash_signatures(kept.drop("snapshot"))), k)
        out = kept.join(gone.select("doc_id"), "doc_id", "left_anti").withColumn("batch", F.lit(k))
        out.write.partitionBy("snapshot", "batch").mode("overwrite").option("partitionOverwriteMode", "dynamic").parquet(f"{base}/corpus")
        kept.unpersist()

    _refresh(spark, d, step, base)
    corpus = spark.read.schema("doc_id long, text string, snapshot int, batch int").parquet(f"{base}/corpus")
    return corpus.select("doc_id", "snapshot", F.md5("text").alias("text_md5"))


_FLAGS = ("words", "mean_word", "symbols", "bullets", "ellipses", "no_alpha", "stops")
_KEPT = f"""with ok as (select doc_id, text, source from documents where lang = 'en' and doc_id in (select doc_id from (select *, {M._DOC_FLAGS} from ({M._DOC_INPUTS})) where not ({" or ".join(f"f_{x}" for x in _FLAGS)}))),
 {M._BAND.removeprefix("with ").replace("from documents", "from ok")}, m as (select band, key, min(doc_id) as witness from bands group by 1, 2)
 select doc_id, {M.SNAP} as snapshot, md5(text) as text_md5 from ok where doc_id not in (select doc_id from bands join m using (band, key) where doc_id <> witness)"""

ORACLES = {
    "stream_tumbling": "select strftime(ts, '%Y-%m-%d') as day, event_type, count(*) as n from events group by 1, 2",
    "stream_sliding": "select strftime(s, '%Y-%m-%d %H:%M') as start, count(*) as n from (select date_trunc('hour', ts) - to_hours(k) as s from events cross join (values (0), (1)) v(k)) group by 1",
    "stream_session": "with g as (select user_id, ts, case when ts - lag(ts) over w < interval 8 hours then 0 else 1 end as new from events window w as (partition by user_id order by ts)), i as (select *, sum(new) over (partition by user_id order by ts) as s from g) select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, count(*) as n from i group by user_id, s",
    "stream_watermark_late": "with e as (select event_id, strftime(ts, '%Y-%m-%d') as day, date_diff('day', date '2024-01-01', ts::date) as i from events), k as (select *, max(i) filter (event_id % 20 <> 0) over (partition by i // 6) as open_day from e) select day, count(*) as n from k where event_id % 20 <> 0 or i = open_day group by 1",
    "stream_dedup": "select distinct user_id, event_type, strftime(ts, '%Y-%m-%d') as day from events",
    "stream_static_join": "select doc_id, lang, quality from documents join labels using (doc_id)",
    "stream_stream_join": "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.event_type = 'click' and p.event_type = 'purchase' and c.user_id = p.user_id and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour",
    "stream_incremental_lsh": M.oracle_sql()["lsh_dropped"],
    "stream_web_track": _KEPT,
    "stream_funnel": "select lang, count(*) as docs, count_if(n_chars >= 300) as kept from documents group by 1",
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [stream_tumbling, stream_sliding, stream_session, stream_watermark_late, stream_dedup, stream_static_join, stream_stream_join, stream_funnel, stream_incremental_lsh, stream_web_track]
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
