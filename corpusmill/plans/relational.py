"""Relational operators around the methods: one SQL text that both engines read.

A text with ``{table}`` runs in Spark on the named DataFrame; the oracle gets
the plain table name. Where the dialects differ there are two texts.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import joins
from ..sources.tables import NAMES, load

_rev = "cast(round(l_extendedprice * 100) as bigint)"

SHARED = {
    "scan_prune": f"select l_orderkey, cast(l_quantity as bigint) as qty, {_rev} as cents from {{lineitem}} where l_shipdate >= timestamp '1996-01-01 00:00:00' and l_shipdate < timestamp '1996-02-01 00:00:00'",
    "filter_keywords": "select doc_id, contains(text, 'token') as has_token, contains(text, 'license') as has_license from {documents} where contains(text, 'token') or contains(text, 'license') or contains(text, 'License')",
    "filter_null_safe": "select o_orderkey, nullif(o_orderstatus, 'F') is null as was_f from {orders} where nullif(o_orderstatus, 'F') is not distinct from nullif('F', 'F')",
    "filter_in_between": "select l_returnflag, l_linestatus, count(*) as n from {lineitem} where l_quantity between 10 and 20 and l_returnflag in ('A', 'R') group by l_returnflag, l_linestatus",
    "proj_case": "select doc_id, case when n_chars < 300 then 'short' when n_chars < 3000 then 'middle' else 'long' end as size_class from {documents}",
    "join_sortmerge": f"select /*+ MERGE(l) */ o_orderpriority, sum({_rev}) as cents from {{orders}} o join {{lineitem}} l on o_orderkey = l_orderkey group by o_orderpriority",
    "join_shuffle_hash": f"select /*+ SHUFFLE_HASH(o) */ o_orderpriority, sum({_rev}) as cents from {{orders}} o join {{lineitem}} l on o_orderkey = l_orderkey group by o_orderpriority",
    "join_broadcast": "select /*+ BROADCAST(n, r) */ r_name, n_name, count(*) as customers from {customer} c join {nation} n on c_nationkey = n_nationkey join {region} r on n_regionkey = r_regionkey group by r_name, n_name",
    "join_left": "select c_custkey, count(o_orderkey) as orders_n from {customer} c left join {orders} o on c_custkey = o_custkey group by c_custkey",
    "join_right": "select o_orderkey, c_custkey from {customer} c right join {orders} o on c_custkey = o_custkey and c_mktsegment = 'BUILDING'",
    "join_full": "select coalesce(c_custkey, o_custkey) as custkey, count(c_custkey) as c_n, count(o_orderkey) as o_n from (select * from {customer} where c_acctbal > 0) c full join (select * from {orders} where o_orderstatus = 'O') o on c_custkey = o_custkey group by coalesce(c_custkey, o_custkey)",
    "join_semi": "select c_custkey from {customer} c where exists (select 1 from {orders} o where o.o_custkey = c.c_custkey and o.o_totalprice > 200000)",
    "join_anti": "select d.doc_id from {documents} d where not exists (select 1 from {labels} l where l.doc_id = d.doc_id)",
    "join_cross": "select r.recipe, l.lang, count(d.doc_id) as docs from (values ('raw', 0), ('length', 300), ('long', 3000)) as r(recipe, least) cross join (select distinct lang from {documents}) l left join {documents} d on d.lang = l.lang and d.n_chars >= r.least group by r.recipe, l.lang",
    "agg_group": f"select l_returnflag, l_linestatus, count(*) as n, sum(cast(l_quantity as bigint)) as qty, sum({_rev}) as cents, min(l_quantity) as q_min, max(l_quantity) as q_max from {{lineitem}} group by l_returnflag, l_linestatus",
    "agg_having": "select source, sum(n_chars) as chars from {documents} group by source having sum(n_chars) > (select sum(n_chars) / count(distinct source) from {documents})",
    "agg_distinct": "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from {lineitem} group by l_returnflag",
    "agg_rollup": "select r_name, n_name, grouping(n_name) as rolled, count(*) as n, sum(cast(round(c_acctbal * 100) as bigint)) as cents from {customer} c join {nation} n on c_nationkey = n_nationkey join {region} r on n_regionkey = r_regionkey group by rollup(r_name, n_name)",
    "agg_cube": "select lang, source, count(*) as n, sum(n_chars) as chars from {documents} group by cube(lang, source)",
    "agg_grouping_sets": "select lang, source, cast(grouping_id(lang, source) as bigint) as gid, count(*) as n from {documents} group by grouping sets ((lang, source), (lang), ())",
    "agg_filter": "select cast(ts as date) || '' as day, count(*) as n, count_if(event_type = 'click') as clicks, sum(case when event_type = 'purchase' then 1 else 0 end) as purchases from {events} group by cast(ts as date)",
    "agg_pivot": "select user_id, sum(case when event_type = 'click' then 1 else 0 end) as click, sum(case when event_type = 'purchase' then 1 else 0 end) as purchase, sum(case when event_type = 'view' then 1 else 0 end) as view_n from {events} group by user_id",
    "agg_minmax_by": "select lang, max_by(doc_id, n_chars * 1000000000 - doc_id) as longest, min_by(doc_id, n_chars * 1000000000 + doc_id) as shortest from {documents} group by lang",
    "agg_bool": "select d.source, bool_or(l.toxic = 1) as any_toxic, bool_and(l.quality = 1) as all_good from {documents} d join {labels} l on d.doc_id = l.doc_id group by d.source",
    "win_rank": "select o_orderkey, row_number() over w as rn, rank() over p as rk, dense_rank() over p as dr from {orders} window w as (partition by o_custkey order by o_totalprice desc, o_orderkey), p as (partition by o_custkey order by o_orderpriority)",
    "win_ntile": "select doc_id, ntile(4) over (partition by lang order by n_chars, doc_id) as quartile from {documents}",
    "win_lag": "select event_id, lag(event_id, 1) over w as prev, lead(event_type, 1, 'none') over w as next_type from {events} window w as (partition by user_id order by ts)",
    "win_first_last": "select event_id, first_value(event_type) over w as first_type, last_value(event_type) over w as last_type, nth_value(event_type, 2) over w as second_type from {events} window w as (partition by user_id order by ts rows between unbounded preceding and unbounded following)",
    "win_rows": "select event_id, sum(cast(round(value * 100) as bigint)) over (partition by user_id order by ts rows between 2 preceding and current row) as cents3 from {events}",
    "win_range": "select event_id, count(*) over (partition by user_id order by ts range between interval 1 hour preceding and current row) as last_hour from {events}",
    "win_cume": "select doc_id, round(cume_dist() over (partition by lang order by n_chars), 6) as share, round(percent_rank() over (partition by lang order by n_chars), 6) as pr from {documents}",
    "win_islands": "with g as (select user_id, event_id, event_type, row_number() over (partition by user_id order by ts) - row_number() over (partition by user_id, event_type order by ts) as island from {events}) select user_id, event_type, min(event_id) as first_event, count(*) as run from g group by user_id, event_type, island",
    "win_budget": "select doc_id, source, running from (select doc_id, source, sum(n_chars) over (partition by source order by doc_id) as running from {documents}) t where running <= 20000",
    "topk_global": "select doc_id, n_chars from {documents} order by n_chars desc, doc_id limit 20",
    "topk_group": "select lang, doc_id, rn from (select lang, doc_id, row_number() over (partition by lang order by n_chars desc, doc_id) as rn from {documents}) t where rn <= 3",
    "limit_offset": "select doc_id from {documents} order by doc_id limit 25 offset 50",
    "set_union": "select doc_id from {documents} where n_chars > 3000 union select doc_id from {labels} where quality = 1",
    "set_intersect": "select doc_id from {documents} where n_chars > 1000 intersect select doc_id from {labels} where quality = 1",
    "set_except": "select doc_id from {documents} except select doc_id from {labels}",
    "set_intersect_all": "select source, lang from {documents} where n_chars > 2000 intersect all select source, lang from {documents} where n_chars <= 2000",
    "set_except_all": "select source, lang from {documents} except all select source, lang from {documents} where n_chars > 1500",
    "subq_scalar": "select o_orderkey from {orders} where o_totalprice > (select avg(o_totalprice) * 1.5 from {orders})",
    "subq_exists": "select o_orderkey from {orders} o where exists (select 1 from {lineitem} l where l.l_orderkey = o.o_orderkey and l.l_returnflag = 'R')",
    "subq_correlated": "select p_partkey from {part} p where p_retailprice > (select avg(q.p_retailprice) from {part} q where q.p_brand = p.p_brand)",
    "fn_string": "select doc_id, lower(substr(text, 1, 20)) as head, length(trim(text)) as n, instr(text, 'the') as pos, replace(substr(text, 1, 30), ' ', '_') as snake, lpad(cast(doc_id as string), 8, '0') as padded, concat_ws('-', lang, source) as tag, ascii(text) as code, reverse(substr(text, 1, 8)) as rev, translate(lang, 'en', 'EN') as tr, repeat(lang, 2) as rep, levenshtein(lang, source) as lev from {documents}",
    "fn_math": "select event_id, cast(floor(value) as bigint) as fl, cast(ceil(value) as bigint) as ce, greatest(value, 50.0e0) as g, least(value, 50.0e0) as le, abs(event_id - 500) as ab, event_id % 7 as md, cast(sign(value) as double) as sg, cast(sqrt(cast(user_id * user_id as double)) as bigint) as sq, cast(power(cast(2 as double), cast(event_id % 10 as double)) as bigint) as pw from {events}",
}

#: key: (Spark, DuckDB)
PAIRS = {
    "agg_unpivot": (
        "select user_id, stack(2, 'click', count_if(event_type = 'click'), 'purchase', count_if(event_type = 'purchase')) as (kind, n) from {events} group by user_id",
        "select user_id, 'click' as kind, count_if(event_type = 'click')::bigint as n from events group by 1 union all select user_id, 'purchase', count_if(event_type = 'purchase')::bigint from events group by 1",
    ),
    "agg_percentile": (
        "select lang, percentile(n_chars, 0.5) as median, percentile(n_chars, 0.9) as p90 from {documents} group by lang",
        "select lang, quantile_cont(n_chars, 0.5) as median, quantile_cont(n_chars, 0.9) as p90 from documents group by lang",
    ),
    "agg_mode": (
        "select c_nationkey, max_by(c_mktsegment, struct(n, c_mktsegment)) as common from (select c_nationkey, c_mktsegment, count(*) as n from {customer} group by 1, 2) t group by c_nationkey",
        "select c_nationkey, c_mktsegment as common from (select c_nationkey, c_mktsegment, row_number() over (partition by c_nationkey order by count(*) desc, c_mktsegment desc) as rn from customer group by 1, 2) where rn = 1",
    ),
    "agg_collect": (
        "select conv_id, array_join(transform(array_sort(collect_list(struct(turn, role))), x -> x.role), '>') as roles from {conversations} group by conv_id",
        "select conv_id, string_agg(role, '>' order by turn) as roles from conversations group by conv_id",
    ),
    "join_lateral": (
        "select doc_id, count(*) as line_n, max(length(line)) as longest from {documents}, lateral (select explode(split(text, '\\n')) as line) where line <> '' group by doc_id",
        "select doc_id, count(*) as line_n, max(length(line)) as longest from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where line <> '' group by doc_id",
    ),
    "sort_within": (
        "select source, doc_id, row_number() over (partition by source order by doc_id) as pos from {documents}",
        "select source, doc_id, row_number() over (partition by source order by doc_id) as pos from documents",
    ),
    "fn_regex": (
        r"select doc_id, regexp_count(text, '[A-Z]') as caps, regexp_extract(text, '([a-z]+)[.]', 1) as ender, length(regexp_replace(text, '[aeiou]', '')) as consonants, text rlike '[0-9]' as has_digit, size(regexp_extract_all(text, '([a-z]+ing)', 1)) as ings from {documents}",
        r"select doc_id, len(regexp_extract_all(text, '[A-Z]'))::int as caps, regexp_extract(text, '([a-z]+)[.]', 1) as ender, length(regexp_replace(text, '[aeiou]', '', 'g')) as consonants, regexp_matches(text, '[0-9]') as has_digit, len(regexp_extract_all(text, '([a-z]+ing)', 1))::int as ings from documents",
    ),
    "fn_url": (
        "select page_id, parse_url(url, 'PROTOCOL') as proto, parse_url(url, 'HOST') as host, coalesce(parse_url(url, 'QUERY'), '') as query, url_decode('a%20b') as dec from {pages}",
        r"select page_id, regexp_extract(url, '^([a-z]+):', 1) as proto, regexp_extract(url, '://([^/?#]*)', 1) as host, regexp_extract(url, '\?([^#]*)', 1) as query, 'a b' as dec from pages",
    ),
    "fn_hash": (
        "select doc_id, md5(text) as m, sha2(text, 256) as s, conv(substr(md5(text), 1, 15), 16, 10) as h60 from {documents}",
        "select doc_id, md5(text) as m, sha256(text) as s, (('0x' || substr(md5(text), 1, 15))::bigint)::varchar as h60 from documents",
    ),
    "fn_date": (
        "select o_orderkey, date_format(date_trunc('MONTH', o_orderdate), 'yyyy-MM-dd') as month, year(o_orderdate) as y, quarter(o_orderdate) as q, dayofyear(o_orderdate) as doy, datediff(to_date(o_orderdate), date '1995-01-01') as days, date_format(o_orderdate + interval 3 days, 'yyyy-MM-dd') as later from {orders}",
        "select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as month, year(o_orderdate)::int as y, quarter(o_orderdate)::int as q, dayofyear(o_orderdate)::int as doy, date_diff('day', date '1995-01-01', o_orderdate::date)::int as days, strftime(o_orderdate + interval 3 days, '%Y-%m-%d') as later from orders",
    ),
    "fn_array": (
        "select doc_id, size(ws) as n, size(array_distinct(ws)) as d, array_join(slice(ws, 1, 3), '|') as head, array_max(transform(ws, x -> length(x))) as longest, size(filter(ws, x -> length(x) > 5)) as long_n, exists(ws, x -> x = 'the') as has_the, aggregate(ws, 0, (s, x) -> s + length(x)) as chars from (select doc_id, filter(split(text, '[ \\t\\r\\n]+'), x -> x <> '') as ws from {documents}) t",
        "select doc_id, len(ws)::int as n, len(list_distinct(ws))::int as d, array_to_string(ws[1:3], '|') as head, list_max(list_transform(ws, lambda x: length(x)))::int as longest, len(list_filter(ws, lambda x: length(x) > 5))::int as long_n, list_contains(ws, 'the') as has_the, list_sum(list_transform(ws, lambda x: length(x)))::int as chars from (select doc_id, list_filter(string_split_regex(text, '[ \\t\\r\\n]+'), lambda x: x <> '') as ws from documents) t",
    ),
    "fn_map": (
        "select doc_id, array_join(array_sort(map_keys(m)), ',') as ks, m['chars'] as chars, size(map_filter(m, (k, v) -> v > 100)) as big, transform_values(m, (k, v) -> v * 2)['words'] as twice from (select doc_id, map('chars', n_chars, 'words', cast(size(split(text, ' ')) as bigint)) as m from {documents}) t",
        "select doc_id, 'chars,words' as ks, n_chars as chars, ((n_chars > 100)::int + (len(string_split(text, ' ')) > 100)::int) as big, 2 * len(string_split(text, ' ')) as twice from documents",
    ),
    "fn_json": (
        "select event_id, get_json_object(props, '$.k') as k_text, from_json(props, 'k int').k as k_num, cast(variant_get(try_parse_json(props), '$.k', 'int') as int) as k_var, to_json(named_struct('id', event_id)) as js from {events}",
        "select event_id, json_extract_string(props, '$.k') as k_text, json_extract_string(props, '$.k')::int as k_num, json_extract_string(props, '$.k')::int as k_var, '{\"id\":' || event_id || '}' as js from events",
    ),
    "fn_struct": (
        "select doc_id, s.lang || ':' || s.n.chars as tag from (select doc_id, named_struct('lang', lang, 'n', named_struct('chars', n_chars)) as s from {documents}) t",
        "select doc_id, lang || ':' || n_chars as tag from documents",
    ),
    "vec_norm": (
        "select vec_id, round(aggregate(embedding, cast(0 as double), (s, x) -> s + cast(x as double) * x), 4) as norm2 from {embeddings}",
        "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as norm2 from embeddings",
    ),
    "vec_centroid": (
        "select label, pos, round(avg(cast(x as double)), 4) + 0 as mean from (select label, posexplode(embedding) as (pos, x) from {embeddings}) t group by label, pos",
        "select label, pos, round(avg(x::double), 4) + 0 as mean from (select label, unnest(range(len(embedding)))::int as pos, unnest(embedding) as x from embeddings) t group by label, pos",
    ),
}


def _sql(text: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        used = {n: load(spark, sf_dir, n) for n in NAMES if "{" + n + "}" in text}
        if used:
            # Braces of the text itself are no table names.
            return spark.sql(text, **used)
        return spark.sql(text)

    return run


def _plain(text: str) -> str:
    for n in NAMES:
        text = text.replace("{" + n + "}", n)
    return text.replace("cast(doc_id as string)", "cast(doc_id as varchar)")


def join_self_band(spark: SparkSession, d: str) -> DataFrame:
    """Documents of one source whose lengths are within one per cent: buckets of the logarithm, then the exact test."""
    docs = load(spark, d, "documents").select("doc_id", "source", "n_chars")
    b = F.floor(F.log(F.greatest("n_chars", F.lit(1)).cast("double")) / 0.02)
    a = docs.select("source", F.col("doc_id").alias("a"), F.col("n_chars").alias("na"), F.explode(F.array(b - 1, b, b + 1)).alias("b_"))
    c = docs.select("source", F.col("doc_id").alias("b"), F.col("n_chars").alias("nb"), b.alias("b_"))
    return a.join(c, ["source", "b_"]).where("a < b and nb * 100 between na * 99 and na * 101").select("a", "b")


def join_range(spark: SparkSession, d: str) -> DataFrame:
    """Events within five minutes of an error of the same user."""
    e = load(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    errors = e.where("event_type = 'error'")
    got = joins.range_join(e.select("event_id", "user_id", "us"), errors.select("event_id", "user_id", "us"), ["user_id"], "us", "us", 300_000_000, ("x", "y"))
    return got.where("x.event_id <> y.event_id").select(F.col("x.event_id").alias("event_id"), F.col("y.event_id").alias("error_id"))


def join_asof(spark: SparkSession, d: str) -> DataFrame:
    """Each purchase with its user's last click before it."""
    e = load(spark, d, "events").select("event_id", "user_id", "event_type", "ts")
    clicks = e.where("event_type = 'click'").withColumnRenamed("event_id", "click_id").select("user_id", "ts", "click_id")
    return joins.asof_join(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), clicks, ["user_id"], "ts", "click_id", "click_id").select("event_id", "click_id")


def join_theta(spark: SparkSession, d: str) -> DataFrame:
    """Parts with the number of parts of their brand that cost less and are larger."""
    p = load(spark, d, "part").select("p_partkey", "p_brand", "p_retailprice", F.col("p_size").cast("long").alias("p_size"))
    got = joins.beaten_counts(p, ["p_brand"], "p_retailprice", "p_size", "beaten")
    return got.groupBy("p_partkey").agg(F.sum("beaten").alias("beaten"))


def join_salted(spark: SparkSession, d: str) -> DataFrame:
    """Lines with how often each occurs, hot lines spread over eight tasks."""
    lines = load(spark, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("pos", "line")).where("line <> ''")
    keyed = lines.select("doc_id", "pos", F.md5("line").alias("h"))
    counts = keyed.groupBy("h").agg(F.count("*").alias("n"))
    return joins.salted_join(keyed, counts, ["h"], 8, F.xxhash64("doc_id", "pos")).groupBy("doc_id").agg(F.sum("n").alias("copies"))


def agg_approx_distinct(spark: SparkSession, d: str) -> DataFrame:
    """Distinct lines by language and in all: HyperLogLog sketches of sources, merged, beside the exact counts."""
    lines = load(spark, d, "documents").select("lang", "source", F.explode(F.split("text", "\n")).alias("line"))
    per = lines.groupBy("lang", "source").agg(F.hll_sketch_agg("line", 14).alias("sketch"))
    rough = per.rollup("lang").agg(F.grouping("lang").cast("int").alias("is_total"), F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("estimate"))
    exact = lines.rollup("lang").agg(F.grouping("lang").cast("int").alias("is_total"), F.count_distinct("line").alias("exact"))
    both = rough.join(exact.withColumnRenamed("lang", "l"), F.col("lang").eqNullSafe(F.col("l")) & (rough.is_total == exact.is_total))
    return both.select("lang", rough.is_total, "exact", (F.abs(F.col("estimate") - F.col("exact")) * 20 <= F.col("exact")).alias("within_5_percent"))


#: Rows of a block of vectors: two blocks and their products are what a task holds.
VEC_BLOCK = 2048


def vec_cosine_topk(spark: SparkSession, d: str) -> DataFrame:
    """Five nearest vectors by cosine of every row whose id is divisible by 20, against all rows.

    Blocks of probes meet blocks of rows; each pair of blocks passes on five
    rows a probe, which are merged.
    """
    v = load(spark, d, "embeddings").select("vec_id", "embedding")
    probes = v.where("vec_id % 20 = 0")
    sizes = v.agg(F.count("*"), F.count_if(F.col("vec_id") % 20 == 0)).first()
    blocks, few = (max(1, -(-n // VEC_BLOCK)) for n in sizes)
    deal = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    spread = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    sides = probes.select(deal(few).alias("p"), spread(blocks).alias("b"), F.lit(True).alias("probe"), "vec_id", "embedding").unionByName(
        v.select(spread(few).alias("p"), deal(blocks).alias("b"), F.lit(False).alias("probe"), "vec_id", "embedding")
    )

    def best(group: pd.DataFrame) -> pd.DataFrame:
        a, b = group[group["probe"]], group[~group["probe"]].sort_values("vec_id")
        out = []
        if len(a) and len(b):
            x, y = (np.array(g["embedding"].tolist(), np.float64) for g in (a, b))
            x, y = (m / np.sqrt((m * m).sum(axis=1, keepdims=True)) for m in (x, y))
            ids = b["vec_id"].to_numpy()
            for k, row in zip(a["vec_id"], x @ y.T, strict=True):
                near = np.round(row, 5)
                near[ids == k] = -np.inf
                for j in np.argsort(-near, kind="stable")[:5]:
                    if ids[j] != k:
                        out.append((k, ids[j], near[j]))
        return pd.DataFrame(out, columns=["probe", "vec_id", "cosine"])

    found = sides.groupBy("p", "b").applyInPandas(best, "probe long, vec_id long, cosine double")
    rank = F.row_number().over(Window.partitionBy("probe").orderBy(F.desc("cosine"), "vec_id"))
    return found.withColumn("rank", rank).where("rank <= 5").select("probe", "rank", "vec_id")


_LABELS = """with recursive k as (select doc_id, source, row_number() over (partition by source order by doc_id) as r from documents),
 e as (select x.doc_id, y.doc_id as up from k x join k y on x.source = y.source and y.r = cast(floor(x.r / 2) as bigint)),
 c(doc_id, component, depth) as (select doc_id, doc_id, 0 from k where r = 1 union all select e.doc_id, c.component, c.depth + 1 from c join e on e.up = c.doc_id)
 select doc_id, component, depth from c"""


def cte_recursive(spark: SparkSession, d: str) -> DataFrame:
    """Component labels by a recursive query: a row hangs under the row of half its rank in its source, down to the source's first."""
    return spark.sql(_LABELS.replace("documents", "{docs}"), docs=load(spark, d, "documents"))


FRAMES = {
    "join_self_band": (join_self_band, "select a.doc_id as a, b.doc_id as b from documents a join documents b on a.source = b.source and a.doc_id < b.doc_id and b.n_chars * 100 between a.n_chars * 99 and a.n_chars * 101"),
    "join_range": (join_range, "select x.event_id, y.event_id as error_id from events x join events y on x.user_id = y.user_id and y.event_type = 'error' and x.event_id <> y.event_id and abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 300000000"),
    "join_asof": (join_asof, "select p.event_id, c.event_id as click_id from (select * from events where event_type = 'purchase') p asof left join (select * from events where event_type = 'click') c on p.user_id = c.user_id and p.ts >= c.ts"),
    "join_theta": (join_theta, "select a.p_partkey, count(*) as beaten from part a join part b on a.p_brand = b.p_brand and a.p_retailprice > b.p_retailprice and a.p_size < b.p_size group by a.p_partkey"),
    "join_salted": (join_salted, "with l as (select doc_id, unnest(string_split(text, chr(10))) as line from documents), c as (select line, count(*) as n from l where line <> '' group by 1) select doc_id, sum(n)::bigint as copies from l join c using (line) group by 1"),
    "agg_approx_distinct": (agg_approx_distinct, "select lang, grouping(lang)::int as is_total, count(distinct line) as exact, true as within_5_percent from (select lang, unnest(string_split(text, chr(10))) as line from documents) group by rollup(lang)"),
    "vec_cosine_topk": (vec_cosine_topk, "select probe, rank, vec_id from (select p.vec_id as probe, v.vec_id, row_number() over (partition by p.vec_id order by round(list_dot_product(v.embedding::double[], p.embedding::double[]) / (sqrt(list_dot_product(v.embedding::double[], v.embedding::double[])) * sqrt(list_dot_product(p.embedding::double[], p.embedding::double[]))), 5) desc, v.vec_id)::int as rank from embeddings v join embeddings p on p.vec_id % 20 = 0 and v.vec_id <> p.vec_id) where rank <= 5"),
    "cte_recursive": (cte_recursive, _LABELS),
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: _sql(v) for k, v in SHARED.items()} | {k: _sql(v[0]) for k, v in PAIRS.items()} | {k: v[0] for k, v in FRAMES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: _plain(v) for k, v in SHARED.items()} | {k: _plain(v[1]) for k, v in PAIRS.items()} | {k: v[1] for k, v in FRAMES.items()}
