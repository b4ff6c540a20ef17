"""Queries of the user surface: UDF kinds, SQL functions and round trips through file formats."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as T
from ..session import scratch
from ..sources import warc
from ..sources.tables import load

_COUNT = f"select doc_id, len({T.SQL_WORDS})::bigint as n from documents"


def _docs(spark, d):
    return load(spark, d, "documents").select("doc_id", "text")


def udf_pandas(spark, d):
    """Word counts by a scalar pandas UDF."""
    f = F.pandas_udf(lambda s: s.map(lambda t: len(T.py_words(t))), "long")
    return _docs(spark, d).select("doc_id", f("text").alias("n"))


def udf_iterator(spark, d):
    """The same by an iterator UDF, which could load a model once per worker."""

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        split = T.py_words
        for b in batches:
            yield b.map(lambda t: len(split(t)))

    return _docs(spark, d).select("doc_id", F.pandas_udf(run, "long")("text").alias("n"))


def udaf_grouped(spark, d):
    """Longest paragraph per language by a grouped-aggregate UDF over bounded numbers."""
    rows = load(spark, d, "documents").select("lang", F.array_max(F.transform(T.paragraphs(F.col("text")), F.length)).alias("n")).where("n is not null")

    def most(s: pd.Series) -> int:
        return int(s.max())

    return rows.groupBy("lang").agg(F.pandas_udf(most, "long", F.PandasUDFType.GROUPED_AGG)("n").alias("longest"))


def udtf_lines(spark, d):
    """Lines by a table function, in a lateral join."""

    class Lines:
        def eval(self, text: str):
            for i, line in enumerate(T.py_paragraphs(text)):
                yield i, len(line)

    spark.udtf.register("corpusmill_lines", F.udtf(Lines, returnType="pos int, n int"))
    return spark.sql("select doc_id, pos, n from {docs}, lateral corpusmill_lines(text)", docs=_docs(spark, d))


def sql_udf(spark, d):
    """A rule as a SQL function."""
    spark.sql("create or replace temporary function corpusmill_size_class(n bigint) returns string return case when n < 300 then 'short' else 'long' end")
    return spark.sql("select doc_id, corpusmill_size_class(n_chars) as size_class from {docs}", docs=load(spark, d, "documents"))


def _round_trip(fmt: str):
    def run(spark, d):
        path = f"{scratch(spark)}/io-{fmt}-{uuid.uuid4().hex}"
        df = load(spark, d, "documents").select("doc_id", "lang", "source", "text")
        writer = df.write.mode("overwrite")
        if fmt == "csv":
            writer = writer.options(escape='"', quoteAll=True)
        writer.option("maxRecordsPerFile", 50_000).format(fmt).save(path)
        reader = spark.read.schema(df.schema).format(fmt)
        if fmt == "csv":
            reader = reader.options(escape='"', multiLine=True)
        return reader.load(path).select("doc_id", "lang", "source", F.md5("text").alias("text_md5"))

    return run


def io_roundtrip_warc(spark, d):
    """Pages written as WARC responses into the shared folder and read again through Spark's own file reader."""
    spark.dataSource.register(warc.WarcSource)
    path = f"{scratch(spark)}/io-warc-{uuid.uuid4().hex}"
    local = path.removeprefix("file://").removeprefix("file:")  # the writer opens files itself
    load(spark, d, "pages").select("url", F.col("html").alias("payload")).write.format("warc").mode("append").save(local)
    return warc.read_binary(spark, f"{path}/*.warc.gz").select("url", "type", F.md5("payload").alias("html_md5"))


_TRIP = "select doc_id, lang, source, md5(text) as text_md5 from documents"


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {f.__name__: f for f in (udf_pandas, udf_iterator, udaf_grouped, udtf_lines, sql_udf, io_roundtrip_warc)}
    return found | {f"io_roundtrip_{x}": _round_trip(x) for x in ("parquet", "json", "csv", "orc")}


def oracle_sql() -> dict[str, str]:
    lines = f"select doc_id, (generate_subscripts(p, 1) - 1)::int as pos, length(unnest(p))::int as n from (select doc_id, {T.SQL_PARAGRAPHS} as p from documents)"
    return {
        "udf_pandas": _COUNT, "udf_iterator": _COUNT, "udtf_lines": lines,
        "udaf_grouped": f"select lang, max(length(p))::bigint as longest from (select lang, unnest({T.SQL_PARAGRAPHS}) as p from documents) group by 1",
        "io_roundtrip_warc": "select url, 'response' as type, md5(html) as html_md5 from pages",
        "sql_udf": "select doc_id, case when n_chars < 300 then 'short' else 'long' end as size_class from documents",
    } | {f"io_roundtrip_{x}": _TRIP for x in ("parquet", "json", "csv", "orc")}
