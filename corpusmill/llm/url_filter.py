"""URL filters by a temporal list join.

A list is a log of dated entries: something is added, removed, added again.
Windows over each value turn the log into validity intervals, from an addition
to the next event. A capture is judged by the entries that were active when it
was fetched: an as-of join of captures with intervals.

Lists and captures may both be large and a host may hold a third of all
captures, so captures are not exploded. Distinct hosts are matched with the
list once (a host matches entries for itself and for the domains above it),
their intervals are packed into one short array per host, and a single join
brings that array to the narrow capture rows. Entries for whole urls work alike.

Every join is salted: the rows that may share one hot key are dealt over
``SALTS`` copies of the narrow list side.

Only DataFrame and SQL functions are used. Edge cases: a null url or fetch time
matches nothing and is not blocked; a removal without an addition is ignored; of
events at one time a removal is the last; repeated captures are judged each;
hosts compare in lower case, without port and user part, urls as they are. A
column of the captures with the name of a result column is returned with
``_given`` added to its name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


SALTS = 32
RESULTS = ("host", "n_active", "first_entry", "blocked")


def host_of(url: Column) -> Column:
    """Lower-case host of a url, empty where it has none."""
    return F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def intervals(entries: DataFrame) -> DataFrame:
    """Validity intervals ``(kind, value, since, until)`` of a log ``entries(kind, value, action, at)``."""
    log = entries.where("value is not null and at is not null").withColumn("value", F.when(F.col("kind") == "url", F.col("value")).otherwise(F.lower("value"))).distinct()
    order = Window.partitionBy("kind", "value").orderBy("at", "action")
    return log.withColumn("until", F.lead("at").over(order)).where((F.col("action") == "add") & (F.col("until").isNull() | (F.col("until") > F.col("at")))).select(
        "kind", "value", F.col("at").alias("since"), "until"
    )


def _packed(hits: DataFrame, by: str) -> DataFrame:
    return hits.groupBy(by).agg(F.array_sort(F.collect_set(F.struct("value", "since", "until"))).alias("spans"))


def _salted(left: DataFrame, listed: DataFrame, on: str, varying: list[Column], how: str) -> DataFrame:
    """Join with a copy of ``listed`` for every salt of the rows of ``left``; ``varying`` tells rows of one key apart."""
    salted = left.withColumn("salt", F.pmod(F.xxhash64(*varying), F.lit(SALTS)).cast("int"))
    copies = listed.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return salted.join(copies, [on, "salt"], how).drop("salt")


def judge_captures(captures: DataFrame, entries: DataFrame) -> DataFrame:
    """All rows and columns of ``captures(url, fetched, ...)`` with ``host``, ``n_active``, ``first_entry`` and ``blocked``.

    ``entries.kind`` is ``host`` (exact), ``domain`` (the host or any below it)
    or ``url`` (exact).
    """
    valid = intervals(entries.select("kind", "value", "action", "at"))
    # The captures travel as one struct, so none of their names can meet one used here.
    named = captures.select(F.struct(*[F.col(f"`{c}`") for c in captures.columns]).alias("given"))
    named = named.select("given", F.col("given.url").alias("url"), F.coalesce(host_of(F.col("given.url")), F.lit("")).alias("host"))
    hosts = named.select("host").where("host <> ''").distinct()
    labels = F.split("host", r"\.")
    above = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda k: F.array_join(F.slice(labels, k, F.size(labels)), "."))
    by_domain = _salted(hosts.select("host", F.explode(above).alias("value")), valid.where("kind = 'domain'"), "value", [F.col("host")], "inner")
    by_host = hosts.withColumn("value", F.col("host")).join(valid.where("kind = 'host'"), "value")
    cols = ["host", "value", "since", "until"]
    host_spans = _packed(by_domain.select(cols).unionByName(by_host.select(cols)), "host").withColumnRenamed("spans", "h_spans")
    url_spans = _packed(valid.where("kind = 'url'").withColumn("url", F.col("value")), "url").withColumnRenamed("spans", "u_spans")
    hashed = [F.col("given").getField(f.name) for f in captures.schema if "map<" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
    joined = _salted(_salted(named, host_spans, "host", hashed, "left"), url_spans, "url", hashed, "left")
    none = F.array().cast(host_spans.schema["h_spans"].dataType)
    every = F.concat(F.coalesce("h_spans", none), F.coalesce("u_spans", none))
    active = F.filter(every, lambda s: (s["since"] <= F.col("given.fetched")) & (s["until"].isNull() | (F.col("given.fetched") < s["until"])))
    kept = [F.col("given").getField(c).alias(f"{c}_given" if c.lower() in RESULTS else c) for c in captures.columns]
    return joined.withColumn("active", active).select(
        *kept,
        "host",
        F.size("active").cast("long").alias("n_active"),
        F.array_min(F.transform("active", lambda s: s["value"])).alias("first_entry"),
        (F.size("active") > 0).alias("blocked"),
    )
