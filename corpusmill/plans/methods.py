"""Queries of the methods, baselines, measures and experiment workloads."""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import code as CODE
from ..functions import text as T
from ..operators import extract, keywords, measures, minhash, models, paragraphs, rules
from ..sources.tables import load
from . import fixtures as X
from . import tracks

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_ORACLES: dict[str, str] = {}


def _key(sql: str | None = None, name: str | None = None):
    def add(f):
        _QUERIES[name or f.__name__] = f
        if sql:
            _ORACLES[name or f.__name__] = sql
        return f

    return add


def _docs(spark, d):
    return load(spark, d, "documents")


def _snap(spark, d):
    return _docs(spark, d).withColumn("snapshot", paragraphs.snapshot(F.col("source")))


W, S, P = T.SQL_WORDS, T.SQL_SENTENCES, T.SQL_PARAGRAPHS
SNAP = "(regexp_extract(source, '([0-9]+)$', 1)::int // 5)"


# ---------------------------------------------------------------- rules

@_key(f"select doc_id, len({W})::int as n_words, len({S})::int as n_sentences, len({P})::int as n_paragraphs, length(text)::int as n_text from documents")
def segment_counts(spark, d):
    return _docs(spark, d).select("doc_id", F.size(T.words(F.col("text"))).alias("n_words"), F.size(T.sentences(F.col("text"))).alias("n_sentences"), F.size(T.paragraphs(F.col("text"))).alias("n_paragraphs"), F.length("text").alias("n_text"))


@_key("select doc_id, n_chars, n_chars >= 300 as keep_length from documents")
def length_rule(spark, d):
    return rules.score_length(_docs(spark, d).select("doc_id", "n_chars"))


_BUL = ", ".join(f"'{b}'" for b in rules.BULLETS)
_STOP = ", ".join(f"'{s}'" for s in rules.STOP_WORDS)
_DOC_INPUTS = f"""select doc_id, n_words, word_chars, symbols, n_sentences, bullets, ellipses, no_alpha, stops from (
 select doc_id, len(w)::bigint as n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::bigint as word_chars,
 (len(regexp_extract_all(text, '#')) + len(regexp_extract_all(text, '\\.\\.\\.')) + len(regexp_extract_all(text, '…')))::bigint as symbols, len(s)::bigint as n_sentences,
 len(list_filter(s, lambda x: substr(x, 1, 1) in ({_BUL})))::bigint as bullets, len(list_filter(s, lambda x: ends_with(x, '...') or ends_with(x, '…')))::bigint as ellipses,
 len(list_filter(w, lambda x: not regexp_matches(x, '\\p{{L}}')))::bigint as no_alpha,
 len(list_intersect([{_STOP}], list_transform(w, lambda x: regexp_replace(lower(x), '^[.,;:!?]+|[.,;:!?]+$', '', 'g'))))::bigint as stops
 from (select doc_id, text, {W} as w, {S} as s from documents))"""
_DOC_FLAGS = """n_words < 50 or n_words > 100000 as f_words, n_words > 0 and (word_chars < 3 * n_words or word_chars > 10 * n_words) as f_mean_word,
 n_words > 0 and 10 * symbols > n_words as f_symbols, n_words > 0 and 10 * bullets > 9 * n_sentences as f_bullets, n_words > 0 and 10 * ellipses > 3 * n_sentences as f_ellipses,
 n_words > 0 and 5 * no_alpha > n_words as f_no_alpha, stops < 2 as f_stops"""


@_key(f"select *, {_DOC_FLAGS} from ({_DOC_INPUTS})")
def rules_document(spark, d):
    return rules.score_document_rules(_docs(spark, d).select("doc_id", "text")).drop("text")


@_key(f"select rule, hits, (hits * 1000000 // (select count(*) from documents))::bigint as share_ppm from (unpivot (select {', '.join(f'count_if({f}) as {f}' for f in ('f_words', 'f_mean_word', 'f_symbols', 'f_bullets', 'f_ellipses', 'f_no_alpha', 'f_stops'))} from (select *, {_DOC_FLAGS} from ({_DOC_INPUTS}))) on columns(*) into name rule value hits)")
def rule_report(spark, d):
    return measures.rule_report(rules.score_document_rules(_docs(spark, d).select("doc_id", "text")))


_REP = f"""select doc_id, length(text)::bigint as n_text, len(s)::bigint as n_sent, (len(s) - len(list_distinct(s)))::bigint as dup_sent,
 (coalesce(list_sum(list_transform(s, lambda x: length(x))), 0) - coalesce(list_sum(list_transform(list_distinct(s), lambda x: length(x))), 0))::bigint as dup_sent_chars,
 len(p)::bigint as n_para, (len(p) - len(list_distinct(p)))::bigint as dup_para,
 (coalesce(list_sum(list_transform(p, lambda x: length(x))), 0) - coalesce(list_sum(list_transform(list_distinct(p), lambda x: length(x))), 0))::bigint as dup_para_chars
 from (select doc_id, text, {S} as s, {P} as p from documents)"""


@_key(f"select *, 10 * dup_sent > 3 * n_sent as f_dup_sent, 5 * dup_sent_chars > n_text as f_dup_sent_chars, 10 * dup_para > 3 * n_sent as f_dup_para, 5 * dup_para_chars > n_text as f_dup_para_chars from ({_REP})")
def rules_sent_para_repetition(spark, d):
    got = rules.score_repetition(_docs(spark, d).select("doc_id", "text"))
    return got.select("doc_id", "n_text", "n_sent", "dup_sent", "dup_sent_chars", "n_para", "dup_para", "dup_para_chars", "f_dup_sent", "f_dup_sent_chars", "f_dup_para", "f_dup_para_chars")


@_key(f"select doc_id, 10 * dup_para > 3 * n_sent as as_printed, 10 * dup_para > 3 * n_para as over_paragraphs from ({_REP})")
def rules_para_denominator_variant(spark, d):
    got = rules.score_repetition(_docs(spark, d).select("doc_id", "text"))
    return got.select("doc_id", F.col("f_dup_para").alias("as_printed"), rules.too_many_paragraphs("paragraph").alias("over_paragraphs"))


def _gram_sql(sizes) -> str:
    return f"""w as (select doc_id, length(text) as t, {W} as ws from documents),
 g as (select doc_id, n, i, array_to_string(ws[i:i + n - 1], ' ') as gram, list_sum(list_transform(ws[i:i + n - 1], lambda x: length(x))) as chars
  from (select doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) as i from w cross join (select unnest([{', '.join(map(str, sizes))}]) as n) where len(ws) >= n)),
 c as (select doc_id, n, gram, count(*) as k, any_value(chars) as chars from g group by 1, 2, 3)"""


@_key(f"""with {_gram_sql(rules.TOP_NGRAM)}, m as (select doc_id, n, max(k) as best from c group by 1, 2),
 b as (select c.doc_id, c.n, max(m.best) as best, max(case when k >= 2 then k * chars else 0 end) as top from c join m on c.doc_id = m.doc_id and c.n = m.n and c.k = m.best group by 1, 2)
 select w.doc_id, s.n, coalesce(best, 0)::bigint as best, coalesce(top, 0)::bigint as top, 100 * coalesce(top, 0) > share * t as flagged
 from w cross join (values (2, 20), (3, 18), (4, 16)) s(n, share) left join b on b.doc_id = w.doc_id and b.n = s.n""")
def rules_top_ngram(spark, d):
    got = rules.score_repetition(_docs(spark, d).select("doc_id", "text"))
    rows = F.array(*[F.struct(F.lit(n).alias("n"), F.col(f"best_{n}").alias("best"), F.col(f"top_{n}").alias("top"), F.col(f"f_top_{n}").alias("flagged")) for n in rules.TOP_NGRAM])
    return got.select("doc_id", F.explode(rows).alias("r")).select("doc_id", "r.*")


@_key(f"""with {_gram_sql(rules.DUP_NGRAM)}, j as (select distinct g.doc_id, g.n, unnest(range(g.i, g.i + g.n)) as at from g join c using (doc_id, n, gram) where k >= 2),
 s as (select j.doc_id, j.n, sum(length(w.ws[j.at])) as cover from j join w using (doc_id) group by 1, 2)
 select w.doc_id, r.n, coalesce(cover, 0)::bigint as cover, 100 * coalesce(cover, 0) > share * t as flagged
 from w cross join (values (5, 15), (6, 14), (7, 13), (8, 12), (9, 11), (10, 10)) r(n, share) left join s on s.doc_id = w.doc_id and s.n = r.n""")
def rules_dup_ngram(spark, d):
    got = rules.score_repetition(_docs(spark, d).select("doc_id", "text"))
    rows = F.array(*[F.struct(F.lit(n).alias("n"), F.col(f"cover_{n}").alias("cover"), F.col(f"f_cover_{n}").alias("flagged")) for n in rules.DUP_NGRAM])
    return got.select("doc_id", F.explode(rows).alias("r")).select("doc_id", "r.*")


_SENT = rf"""p as (select doc_id, unnest({P}) as par, generate_subscripts({P}, 1) as pi from documents),
 s as (select doc_id, pi, unnest({S.replace('text', 'par')}) as sen, generate_subscripts({S.replace('text', 'par')}, 1) as si from p),
 h as (select *, len({W.replace('text', 'sen')}) as n, 10 * len(regexp_extract_all(sen, '\p{{Lu}}')) > 6 * len(regexp_extract_all(sen, '\p{{L}}')) as upper_,
  regexp_full_match(sen, '[0-9 \t.,]*[0-9][0-9 \t.,]*') as numeric_, regexp_full_match(sen, '[0-9]+[ \t]+[a-zA-Z]+') as counter_, len({W.replace('text', 'sen')}) = 1 as one_,
  regexp_matches(sen, '(?i)^sign-in') as sign_, regexp_matches(sen, '(?i)read more.{{3}}$') as more_, regexp_matches(sen, '(?i)items in card') as card_ from s),
 m as (select *, upper_ or numeric_ or counter_ or one_ or sign_ or more_ or card_ as met from h)"""


@_key(f"""with {_SENT} select d.doc_id, coalesce(sum(n), 0)::bigint as words_all, coalesce(sum(n) filter (met), 0)::bigint as words_removed,
 {', '.join(f'count_if({c}_)::bigint as hit_{r}' for c, r in zip(('upper', 'numeric', 'counter', 'one', 'sign', 'more', 'card'), rules.SENTENCE_RULES, strict=True))},
 coalesce(20 * sum(n) filter (met) > sum(n), false) as f_sentences from documents d left join m on m.doc_id = d.doc_id group by d.doc_id""")
def rules_sentence(spark, d):
    return rules.apply_sentence_rules(_docs(spark, d).select("doc_id", "text")).drop("text", "text_clean")


@_key(f"""with {_SENT}, q as (select doc_id, pi, string_agg(sen, ' ' order by si) as line from m where not met group by 1, 2), t as (select doc_id, string_agg(line, chr(10) order by pi) as clean from q group by 1)
 select d.doc_id, md5(coalesce(clean, '')) as clean_md5 from documents d left join t using (doc_id)""")
def sentence_clean_text(spark, d):
    return rules.apply_sentence_rules(_docs(spark, d).select("doc_id", "text")).select("doc_id", F.md5("text_clean").alias("clean_md5"))


# ---------------------------------------------------------------- paragraph and document dedup

def _para_sql(scope: str, keep: str) -> str:
    drop = "n > 1 and rn > 1" if keep == "first" else "n > 1"
    return f"""with p as (select doc_id, {scope} as sc, unnest({P}) as par, generate_subscripts({P}, 1) as pos from documents),
 k as (select *, count(*) over (partition by sc, par) as n, row_number() over (partition by sc, par order by doc_id, pos) as rn from p),
 r as (select doc_id, count_if(not ({drop}))::bigint as n_kept, count_if({drop})::bigint as n_removed, string_agg(par, chr(10) order by pos) filter (not ({drop})) as t from k group by 1)
 select d.doc_id, coalesce(n_kept, 0) as n_kept, coalesce(n_removed, 0) as n_removed, md5(coalesce(t, '')) as text_md5 from documents d left join r using (doc_id)"""


def _para(scope, keep="first"):
    def run(spark, d):
        got = paragraphs.dedup_paragraphs(_snap(spark, d).select("doc_id", "text", "snapshot", "source"), scope=scope, keep=keep)
        return got.select("doc_id", "n_kept", "n_removed", F.md5("text_dedup").alias("text_md5"))

    return run


for _name, _scope, _sql_scope, _keep in (
    ("para_dedup_snapshot", ("snapshot",), SNAP, "first"), ("para_dedup_shard", ("snapshot", "source"), "source", "first"),
    ("para_dedup_all", (), "0", "first"), ("para_dedup_drop_all", (), "0", "none"),
):
    _key(_para_sql(_sql_scope, _keep), _name)(_para(_scope, _keep))


@_key(" union all ".join(f"select '{n}' as scope, sum(n_removed)::bigint as removed from ({_para_sql(s, 'first')})" for n, s in (("shard", "source"), ("snapshot", SNAP), ("all", "0"))))
def para_dedup_gain(spark, d):
    parts = [_para(s)(spark, d).agg(F.lit(n).alias("scope"), F.sum("n_removed").alias("removed")) for n, s in (("shard", ("snapshot", "source")), ("snapshot", ("snapshot",)), ("all", ()))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@_key("select min(doc_id) as doc_id, count(*) as copies from documents group by text")
def exact_dedup(spark, d):
    return paragraphs.dedup_exact(_docs(spark, d))


# ---------------------------------------------------------------- MinHash

_SH = r"""tok as (select doc_id, source, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') as w from documents),
 sh as (select distinct doc_id, array_to_string(w[i:i + least(5, len(w)) - 1], ' ') as g from (select doc_id, w, unnest(range(1, len(w) - least(5, len(w)) + 2)) as i from tok where len(w) > 0)),
 hs as (select distinct doc_id, ('0x' || substr(md5(g), 1, 15))::bigint as h from sh)"""
_SIG = _SH + """, pc as (select i, (('0x' || substr(md5('a:' || i), 1, 15))::bigint + 1)::hugeint as a, (('0x' || substr(md5('b:' || i), 1, 15))::bigint)::hugeint as b from range(117) t(i)),
 sig as (select doc_id, i, min((a * h + b) % 2305843009213693951) as v from hs cross join pc group by 1, 2)"""
_BAND = _SIG + ", bands as (select doc_id, i // 13 as band, md5(string_agg(v::varchar, ',' order by i)) as key from sig group by 1, 2)"


@_key(f"with {_SH} select d.doc_id, count(h) as shingles from documents d left join hs using (doc_id) group by 1")
def shingle_stats(spark, d):
    n = F.pandas_udf(lambda s: s.map(lambda t: len(minhash.shingles(t))), "long")
    return _docs(spark, d).select("doc_id", n("text").alias("shingles"))


@_key(f"with {_SIG} select doc_id, min(v) filter (i = 0)::bigint as first_value, md5(string_agg(v::varchar, ',' order by i)) as sig_md5 from sig group by 1")
def minhash_signature(spark, d):
    got = minhash.minhash_signatures(_docs(spark, d)).where("sig is not null")
    return got.select("doc_id", F.element_at("sig", 1).alias("first_value"), F.md5(F.array_join(F.col("sig").cast("array<string>"), ",")).alias("sig_md5"))


def _bands(spark, d):
    return minhash.lsh_bands(minhash.minhash_signatures(_snap(spark, d)))


@_key(f"with {_BAND} select doc_id, band::int as band, key from bands")
def lsh_band_keys(spark, d):
    return _bands(spark, d).drop("snapshot")


@_key(f"with {_BAND}, z as (select band, key, count(*) as size from bands group by 1, 2) select band::int as band, size, count(*) as buckets from z group by 1, 2")
def lsh_bucket_sizes(spark, d):
    return _bands(spark, d).groupBy("band", "key").agg(F.count("*").alias("size")).groupBy("band", "size").agg(F.count("*").alias("buckets"))


_PAIRS = _BAND + ", pairs as (select x.doc_id as a, y.doc_id as b, count(*) as bands from bands x join bands y on x.band = y.band and x.key = y.key and x.doc_id < y.doc_id group by 1, 2)"


@_key(f"with {_PAIRS} select a, b, bands from pairs")
def lsh_candidate_pairs(spark, d):
    return minhash.candidate_pairs(_bands(spark, d))


@_key(f"with {_BAND}, m as (select band, key, min(doc_id) as witness from bands group by 1, 2 having count(*) > 1) select doc_id, min(witness) as witness from bands join m using (band, key) where doc_id <> witness group by 1")
def lsh_dropped(spark, d):
    return minhash.dedup_lsh(_bands(spark, d))


@_key(f"""with {_BAND}, s as (select doc_id, {SNAP} as snap from documents), m as (select snap, band, key, min(doc_id) as witness from bands join s using (doc_id) group by 1, 2, 3)
 select doc_id, min(witness) as witness from bands join s using (doc_id) join m using (snap, band, key) where doc_id <> witness group by 1""")
def lsh_scope_snapshot(spark, d):
    return minhash.dedup_lsh(_bands(spark, d), ("snapshot",))


#: Each chain hangs together by its middle member; the first of a bucket stays.
_CHAIN_OF = "case when doc_id % 8 in (1, 2, 7) then 'k' || cast(doc_id // 8 as varchar) when doc_id % 8 in (3, 4, 5) then 'l' || cast(doc_id // 8 as varchar) else 'giant' || coalesce(source, '') end"


@_key(f"""with r as ({X.chain_sql()}), f as (select band, key, min(doc_id) as first_id from r group by 1, 2),
 b as (select doc_id, bool_or(doc_id <> first_id) as bucket_drops from r join f using (band, key) group by 1),
 c as (select doc_id, doc_id % 8 in (0, 6) or bool_or(doc_id % 8 in (4, 7)) over (partition by {_CHAIN_OF}) as joined, min(doc_id) over (partition by {_CHAIN_OF}) as least_id from documents where length(text) > 0)
 select doc_id, bucket_drops, joined and doc_id <> least_id as graph_drops from b join c using (doc_id)""")
def lsh_chain_fixture(spark, d):
    rows = X.derived(spark, d, X.chain_sql())
    bucket = minhash.dedup_lsh(rows).select("doc_id", F.lit(True).alias("bucket_drops"))
    first = rows.groupBy("band", "key").agg(F.min("doc_id").alias("a"))
    graph = minhash.dedup_components(rows.join(first, ["band", "key"]).where("doc_id <> a").select("a", F.col("doc_id").alias("b")))
    g = graph.select("doc_id", (F.col("doc_id") != F.col("component")).alias("graph_drops"))
    out = rows.select("doc_id").distinct().join(bucket, "doc_id", "left").join(g, "doc_id", "left")
    return out.select("doc_id", F.coalesce("bucket_drops", F.lit(False)).alias("bucket_drops"), F.coalesce("graph_drops", F.lit(False)).alias("graph_drops"))


@_key(f"""with recursive {_PAIRS}, e as (select a, b from pairs union all select b, a from pairs),
 reach as (select distinct a as x, a as y from e union select reach.x, e.b from reach join e on reach.y = e.a) select x as doc_id, min(y) as component from reach group by 1""")
def components_labels(spark, d):
    return minhash.dedup_components(minhash.candidate_pairs(_bands(spark, d)))


_EXACT = f'with {_SH}, n as (select doc_id, count(*) as n from hs group by 1), b as (select x.doc_id as a, y.doc_id as b, count(*) as "both" from hs x join hs y on x.h = y.h and x.doc_id < y.doc_id group by 1, 2) select a, b, "both", x.n + y.n - "both" as either from b join n x on x.doc_id = a join n y on y.doc_id = b where "both" * 10 >= (x.n + y.n - "both") * 5'


@_key(_EXACT)
def jaccard_pairs(spark, d):
    return minhash.jaccard_pairs(_docs(spark, d))


@_key(f'with {_PAIRS}, t as (select * from ({_EXACT})) select floor("both" * 10.0e0 / either)::bigint as tenths, count(*) as pairs, count(p.bands) as found from t left join pairs p on p.a = t.a and p.b = t.b group by 1')
def lsh_vs_exact(spark, d):
    """Pairs of classes stand for those of their members; only classes in an exact pair are signed. Copies share all bands."""
    docs = _docs(spark, d)
    members, pairs = minhash.jaccard_classes(docs)
    ids = minhash.checkpointed(pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct())
    bands = minhash.checkpointed(minhash.lsh_bands(minhash.minhash_signatures(minhash.rows_of(docs, ids))))
    side = lambda x: bands.select(F.col("doc_id").alias(x), "band", "key")
    found = pairs.select("a", "b").join(side("a"), "a").join(side("b"), ["b", "band", "key"], "left_semi").select("a", "b").distinct()
    sizes = minhash.checkpointed(members.where("doc_id = rep").select("rep", "n", "size"))
    size = lambda x: sizes.select(F.col("rep").alias(x), F.col("size").alias(f"size_{x}"))
    t = pairs.join(found.withColumn("hit", F.lit(True)), ["a", "b"], "left").join(size("a"), "a").join(size("b"), "b")
    t = t.select(F.floor(F.col("both") * 10 / (F.col("na") + F.col("nb") - F.col("both"))).cast("long").alias("tenths"), (F.col("size_a") * F.col("size_b")).alias("k"), F.col("hit").isNotNull().alias("hit"))
    equal = sizes.where("size > 1").select(F.lit(10).cast("long").alias("tenths"), F.expr("size * (size - 1) div 2").alias("k"), F.lit(True).alias("hit"))
    return t.unionByName(equal).groupBy("tenths").agg(F.sum("k").alias("pairs"), F.sum(F.when(F.col("hit"), F.col("k")).otherwise(0)).alias("found"))


@_key("""with w as (select source, doc_id, list_distinct(string_split(substr(text, 1, 200), ' ')) as a from documents where text is not null),
 v as (select a, lag(a) over (partition by source order by doc_id) as b from w),
 t as (select floor(len(list_intersect(a, b)) * 20.0e0 / (len(a) + len(b) - len(list_intersect(a, b))))::bigint as s from v where b is not null)
 select s / 20.0e0 as s, count(*) as pairs, round(1 - power(1 - power(s / 20.0e0, 13), 9), 6) as p from t group by s""")
def lsh_curve(spark, d):
    """How likely the bands find pairs of neighbours in a source, by how similar the words at the heads of their texts are."""
    w = _docs(spark, d).where("text is not null").select("source", "doc_id", F.array_distinct(F.split(F.substring("text", 1, 200), " ", -1)).alias("a"))
    v = w.select("a", F.lag("a").over(Window.partitionBy("source").orderBy("doc_id")).alias("b")).where("b is not null")
    both = F.size(F.array_intersect("a", "b"))
    t = v.select(F.floor(both * 20.0 / (F.size("a") + F.size("b") - both)).alias("s")).groupBy("s").agg(F.count("*").alias("pairs"))
    return t.select((F.col("s") / 20.0).alias("s"), "pairs").withColumn("p", F.round(minhash.collision(F.col("s")), 6))


@_key()
def lsh_param_sweep(spark, d):
    parts = []
    for b, r in ((9, 13), (14, 8), (20, 10), (40, 13)):
        bands = minhash.lsh_bands(minhash.minhash_signatures(_docs(spark, d), b * r), b, r)
        parts.append(minhash.dedup_lsh(bands).agg(F.lit(b).alias("bands"), F.lit(r).alias("rows"), F.count("*").alias("dropped")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# ---------------------------------------------------------------- models and web track

def _language_model(spark, d):
    return models.train_language_model(_docs(spark, d).where(~models.held_out()))


@_key()
def lang_scores(spark, d):
    got = models.score_language(_docs(spark, d).select("doc_id", "text", "lang"), _language_model(spark, d))
    return got.select("doc_id", "lang", "lang_pred", F.round("lang_prob", 4).alias("lang_prob"))


@_key()
def lang_accuracy(spark, d):
    got = lang_scores(spark, d).where(models.held_out())
    return got.groupBy("lang").agg(F.count("*").alias("n"), F.count_if(F.col("lang") == F.col("lang_pred")).alias("correct"))


_H60 = "('0x' || substr(md5(doc_id::varchar), 1, 15))::bigint"


@_key(f"select doc_id, quality as label from (select doc_id, quality, row_number() over (partition by quality order by {_H60}, doc_id) as r from labels) where r <= 40")
def quality_sample(spark, d):
    return models.balanced_sample(load(spark, d, "labels").select("doc_id", F.col("quality").alias("label")), "label", 40)


def _quality_model(spark, d):
    marked = models.annotate(_docs(spark, d), load(spark, d, "labels")).where(~models.held_out())
    return models.train_text_classifier(models.balanced_sample(marked, "label", 1000))


@_key()
def quality_report(spark, d):
    held = models.annotate(_docs(spark, d), load(spark, d, "labels")).where(models.held_out())
    got = models.score_model(held.select("doc_id", "text", "label"), _quality_model(spark, d))
    return models.binary_report(got.withColumn("yes", F.col("p_quality") >= 0.5), "label", "yes")


_WET = f"""select d.doc_id, len(list_filter(string_split_regex(t, '[ \\t\\r\\n\\f]+'), lambda w: w <> ''))::bigint as n_words, lang = 'en' as keep_lang, length(t) >= 300 as keep_length
 from documents d join (with p as (select doc_id, {SNAP} as sc, unnest({P}) as par, generate_subscripts({P}, 1) as pos from documents),
 k as (select *, row_number() over (partition by sc, par order by doc_id, pos) as rn from p)
 select doc_id, coalesce(string_agg(par, chr(10) order by pos) filter (rn = 1), '') as t from documents left join k using (doc_id) group by 1) r using (doc_id)"""


@_key(_WET)
def web_wet_verdicts(spark, d):
    got = paragraphs.dedup_paragraphs(_snap(spark, d).select("doc_id", "text", "lang", "snapshot"), scope=("snapshot",))
    return got.select("doc_id", measures.token_count(F.col("text_dedup")).alias("n_words"), (F.col("lang") == "en").alias("keep_lang"), (F.length("text_dedup") >= 300).alias("keep_length"))


@_key(f"""with v as ({_WET}), f as (select 0 as step, 'input' as stage, count(*) as docs, sum(n_words)::bigint as tokens from v
 union all select 1, 'keep_lang', count_if(keep_lang), sum(n_words) filter (keep_lang)::bigint from v union all select 2, 'keep_length', count_if(keep_lang and keep_length), sum(n_words) filter (keep_lang and keep_length)::bigint from v)
 select *, ((first_value(tokens) over (order by step) - tokens) * 1000000 // first_value(tokens) over (order by step))::bigint as removed_ppm from f""")
def web_funnel(spark, d):
    return measures.funnel(web_wet_verdicts(spark, d), ["keep_lang", "keep_length"])


@_key(f"select s as snapshot, keep_lang, count(*) as docs, sum(n_words)::bigint as tokens from (select v.*, {SNAP} as s from ({_WET}) v join documents using (doc_id)) group by cube(s, keep_lang)")
def snapshot_funnel(spark, d):
    v = web_wet_verdicts(spark, d).join(_snap(spark, d).select("doc_id", "snapshot"), "doc_id")
    return v.cube("snapshot", "keep_lang").agg(F.count("*").alias("docs"), F.sum("n_words").alias("tokens"))


_ROUTE = f"""with texts as (with p as (select doc_id, {SNAP} as sc, unnest({P}) as par, generate_subscripts({P}, 1) as pos from documents),
  k as (select *, row_number() over (partition by sc, par order by doc_id, pos) as rn from p)
  select d.doc_id, any_value(lang) as lang, coalesce(string_agg(par, chr(10) order by pos) filter (rn = 1), '') as text, '' as source from documents d left join k using (doc_id) group by 1),
 judged as (select t.*, len({W})::bigint as n_words, coalesce(lang = 'en', false) as keep_lang, length(text) >= 300 as keep_length, coalesce(quality = 1, false) as keep_model from texts t left join labels using (doc_id)),
 reach as (select doc_id, text, source from judged where keep_lang and keep_length and keep_model), {_BAND.replace("from documents", "from reach")},
 m as (select band, key, min(doc_id) as witness from bands group by 1, 2), gone as (select distinct doc_id from bands join m using (band, key) where doc_id <> witness)
 select doc_id, n_words, keep_lang, keep_length, keep_model, case when keep_lang and keep_length and keep_model then doc_id not in (select doc_id from gone) end as keep_lsh from judged"""


@_key(_ROUTE)
def web_wet_route_verdicts(spark, d):
    """The verdict of every stage of the plain-text route; the given languages and labels stand for the models. ``keep_lsh`` is null where an earlier stage drops the text."""
    got = paragraphs.dedup_paragraphs(_snap(spark, d).select("doc_id", "text", "lang", "snapshot"), scope=("snapshot",))
    no = F.lit(False)
    out = got.join(load(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left").select(
        "doc_id", F.col("text_dedup").alias("text"), measures.token_count(F.col("text_dedup")).alias("n_words"), F.coalesce(F.col("lang") == "en", no).alias("keep_lang"),
        (F.length("text_dedup") >= 300).alias("keep_length"), F.coalesce(F.col("quality") == 1, no).alias("keep_model"),
    )
    out = out.withColumn("reaches", F.expr("keep_lang and keep_length and keep_model"))
    gone = minhash.dedup_lsh(minhash.lsh_bands(minhash.minhash_signatures(out.where("reaches").select("doc_id", "text")))).select("doc_id", F.lit(True).alias("gone"))
    told = out.join(gone, "doc_id", "left").withColumn("keep_lsh", F.when(F.col("reaches"), F.col("gone").isNull()))
    return told.select("doc_id", "n_words", "keep_lang", "keep_length", "keep_model", "keep_lsh")


_STEPS = ("keep_lang", "keep_length", "keep_model", "keep_lsh")


@_key(f"""with v as ({_ROUTE}), f as (select 0 as step, 'input' as stage, count(*) as docs, sum(n_words)::bigint as tokens from v union all
 {' union all '.join(f"select {i + 1}, '{s}', count_if({c}), coalesce(sum(n_words) filter ({c}), 0)::bigint from v" for i, s in enumerate(_STEPS) for c in [' and '.join(_STEPS[: i + 1])])})
 select *, ((first_value(tokens) over (order by step) - tokens) * 1000000 // first_value(tokens) over (order by step))::bigint as removed_ppm from f""")
def web_route_funnel(spark, d):
    """Documents and tokens left after each stage of the whole plain-text route."""
    return measures.funnel(web_wet_route_verdicts(spark, d), list(_STEPS))


@_key()
def web_wet_corpus(spark, d):
    return tracks.web_track_wet(_language_model(spark, d), _quality_model(spark, d)).run(_docs(spark, d)).df.select("doc_id", F.md5("text").alias("text_md5"))


@_key()
def web_warc_corpus(spark, d):
    return tracks.web_track_warc(_language_model(spark, d), _quality_model(spark, d)).run(load(spark, d, "pages")).df.select("doc_id", F.md5("text").alias("text_md5"))


@_key()
def web_warc_verdicts(spark, d):
    """The verdict of every stage; ``keep_lsh`` is null where an earlier stage drops the page."""
    text = extract.extract_main_content(load(spark, d, "pages").select(F.col("page_id").alias("doc_id"), "html")).select("doc_id", "text")
    told = models.score_language(text, _language_model(spark, d))
    repeated = rules.score_repetition(told)
    judged = rules.score_document_rules(repeated)
    cleaned = rules.apply_sentence_rules(judged).drop("text").withColumnRenamed("text_clean", "text")
    out = models.score_model(cleaned, _quality_model(spark, d))
    verdicts = {
        "keep_lang": (F.col("lang_pred") == "en") & (F.col("lang_prob") >= 0.5),
        "keep_repetition": ~rules.any_flag(repeated.columns),
        "keep_rules": ~rules.any_flag([c for c in judged.columns if c not in repeated.columns]),
        "keep_sentences": ~F.col("f_sentences"),
        "keep_model": F.col("p_quality") >= 0.5,
    }
    out = out.withColumns(verdicts).withColumn("reaches_lsh", F.expr(" and ".join(verdicts)))
    gone = minhash.dedup_lsh(minhash.lsh_bands(minhash.minhash_signatures(out.where("reaches_lsh").select("doc_id", "text")))).select("doc_id", F.lit(True).alias("gone"))
    flags = [c for c in out.columns if c.startswith("f_")]
    lsh = F.when(F.col("reaches_lsh"), F.col("gone").isNull()).alias("keep_lsh")
    return out.join(gone, "doc_id", "left").select("doc_id", "n_words", "lang_pred", *flags, *verdicts, lsh)


@_key()
def web_format_stats(spark, d):
    given = _language_model(spark, d), _quality_model(spark, d)
    wet = tracks.web_track_wet(*given).run(_docs(spark, d)).df
    warc = tracks.web_track_warc(*given).run(load(spark, d, "pages")).df
    return measures.dataset_stats(tracks.merge_formats(wet, warc), "format")


# ---------------------------------------------------------------- pages

@_key()
def linearized_text(spark, d):
    return extract.linearize_html(load(spark, d, "pages").select("page_id", "html")).select("page_id", F.length("text").alias("chars"), F.md5("text").alias("text_md5"))


@_key()
def main_content(spark, d):
    return extract.extract_main_content(load(spark, d, "pages").select("page_id", "html")).select("page_id", F.length("text").alias("chars"), F.md5("text").alias("text_md5"))


@_key("select page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) as title, len(regexp_extract_all(html, '<a href='))::int as n_links from pages")
def html_title(spark, d):
    return load(spark, d, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_count("html", F.lit("<a href=")).alias("n_links"))


@_key("""select page_id, len(a)::int as n_links, len(list_filter(a, lambda x: starts_with(x, 'http')))::int as n_absolute, len(regexp_extract_all(regexp_extract(html, '(?s)<nav>.*?</nav>'), '<a href='))::int as n_nav_links
 from (select page_id, html, regexp_extract_all(html, '<a href="([^"]*)"', 1) as a from pages)""")
def html_links(spark, d):
    """Links of a page: all, absolute ones, and those inside the navigation."""
    a = F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), F.lit(1))
    nav = F.regexp_count(F.regexp_extract("html", "(?s)<nav>.*?</nav>", 0), F.lit("<a href="))
    return load(spark, d, "pages").select("page_id", F.size(a).alias("n_links"), F.size(F.filter(a, lambda x: x.startswith("http"))).alias("n_absolute"), nav.alias("n_nav_links"))


def _code(spark, d):
    return X.derived(spark, d, X.code_sql())


def _math(spark, d):
    return X.derived(spark, d, X.math_sql())


@_key(f"select page_id, contains(html, '<code') as has_code_tag, contains(html, '<pre') as has_pre_tag, contains(url, 'blame.php') or contains(url, 'diff.php') as blocked_url from ({X.code_sql()})")
def code_prefilter(spark, d):
    return keywords.score_code_page(_code(spark, d)).drop("html", "url")


#: What the planted classes must give by their own definition: hidden characters, roots, and roots that are ``pre`` or ``tbody``.
_PLANTED_CODE = "(values (0, 0, 1, 1, 0), (1, 0, 1, 0, 0), (2, 0, 1, 0, 0), (3, 0, 1, 0, 1), (5, 13, 0, 0, 0), (6, 13, 1, 0, 0), (7, 12, 0, 0, 0), (8, 0, 1, 1, 0), (9, 0, 1, 1, 0), (10, 0, 2, 2, 0))"


def _planted_code(columns: str) -> str:
    return f"select page_id, {', '.join(f'coalesce({c}, 0)::bigint as {c}' for c in columns.split())} from pages left join {_PLANTED_CODE} p(m, hidden_chars, roots, pre_roots, tbody_roots) on page_id % 12 = m and contains(html, '</article>')"


@_key(_planted_code("hidden_chars"))
def hidden_removed(spark, d):
    return extract.code_pass(_code(spark, d)).select("page_id", "hidden_chars")


@_key(_planted_code("roots pre_roots tbody_roots"))
def code_roots(spark, d):
    return extract.code_pass(_code(spark, d)).select("page_id", "roots", "pre_roots", "tbody_roots")


_FAM = {k: v.replace("'", "''") for k, v in CODE.FAMILIES.items()}


@_key(f"select snippet_id, {', '.join(f"regexp_matches(text, '{p}') as {k}" for k, p in _FAM.items())} from ({X.snippets_sql()})")
def code_snippet_tests(spark, d):
    s = X.derived(spark, d, X.snippets_sql())
    return s.select("snippet_id", *[F.col("text").rlike(p).alias(k) for k, p in CODE.FAMILIES.items()])


@_key(f"""with l as (select snippet_id, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as i from ({X.snippets_sql()})),
 n as (select snippet_id, i, line::bigint as v from l where regexp_full_match(line, '[ ]*[0-9]{{1,9}}[ ]*')),
 r as (select snippet_id, i, gap, count(*) over (partition by snippet_id, gap, i - gap * v, i % gap) as run from n cross join (values (1), (2)) g(gap)),
 x as (select distinct snippet_id, i from r where run >= 3)
 select snippet_id, md5(coalesce(string_agg(line, chr(10) order by l.i) filter (x.i is null), '')) as text_md5 from l left join x using (snippet_id, i) group by 1""")
def line_numbers_removed(spark, d):
    f = F.pandas_udf(lambda s: s.map(CODE.strip_line_numbers), "string")
    return X.derived(spark, d, X.snippets_sql()).select("snippet_id", F.md5(f("text")).alias("text_md5"))


_JOINTS = r"</code></pre>\s*<pre><code>"


@_key(f"select page_id, n::int as before, (n - len(regexp_extract_all(html, '{_JOINTS}')))::int as after from (select page_id, html, len(regexp_extract_all(html, '<pre><code>')) as n from ({X.code_sql()}))")
def code_merge_adjacent(spark, d):
    """Block snippets of a page before and after neighbours are joined."""
    tagged = F.replace(F.replace(F.col("html"), F.lit("<pre><code>"), F.lit("<code-encode>")), F.lit("</code></pre>"), F.lit("</code-encode>"))
    merged = F.pandas_udf(lambda s: s.map(lambda t: t and CODE.merge_adjacent(t)), "string")
    n = lambda c: F.regexp_count(c, F.lit("<code-encode>"))
    return _code(spark, d).select("page_id", tagged.alias("t")).select("page_id", n(F.col("t")).alias("before"), n(merged("t")).alias("after"))


@_key()
def code_pages(spark, d):
    got = tracks.code_track().run(_code(spark, d)).df
    return got.select("page_id", "n_snippets", F.array_join("langs", ",").alias("langs"), F.md5(F.array_join("snippets", "|")).alias("snippets_md5"))


@_key()
def code_vs_main_content(spark, d):
    """Extracted snippets whose text, white space aside, survives in the full-text and in the main-content route."""
    pages = keywords.keep_code_page(_code(spark, d))
    code = extract.code_pass(pages).where("has_code").select("page_id", F.explode("snippets").alias("s"))
    both = extract.linearize_html(extract.extract_main_content(pages.select("page_id", "html"), out="main"), out="full").select("page_id", "main", "full")
    bare = lambda c: F.regexp_replace(c, r"\s+", "")
    j = code.join(both, "page_id").select(*[bare(c).contains(bare("s")).alias(f"in_{c}") for c in ("full", "main")])
    return j.agg(F.count("*").alias("snippets"), F.count_if("in_full").alias("in_full_text"), F.count_if("in_main").alias("in_main_content"))


@_key(f"select page_id, {', '.join(f"contains(html, '{k}') as k{i + 1}" for i, k in enumerate(keywords.MATH_PAGE))} from ({X.math_sql()})")
def math_prefilter(spark, d):
    return keywords.score_math_page(_math(spark, d)).drop("html", "url")


@_key()
def math_formulas(spark, d):
    return extract.formula_rows(keywords.keep_math_page(_math(spark, d))).select("page_id", "pos", "dialect", "display", F.md5("source").alias("source_md5"))


@_key()
def latex_check(spark, d):
    return extract.formula_rows(keywords.keep_math_page(_math(spark, d))).select("page_id", "pos", "ok", "reason")


@_key()
def math_pages(spark, d):
    return extract.math_pass(keywords.keep_math_page(_math(spark, d))).select("page_id", "n_formulas", "valid", "keep")


_PLAIN = " + ".join(f"((length(text) - length(replace(text, '{k}', ''))) // {len(k)})" for k in keywords.PLAIN_MATH)
_KINDS = " + ".join(f"contains(text, '{k}')::bigint" for k in keywords.PLAIN_MATH)
_CMDS = ", ".join(f"'{c}'" for c in keywords.latex_commands())


@_key(f"""select *, latex_hits + plain_hits >= 5 as keep_occurrence, latex_kinds + plain_kinds >= 5 as keep_distinct from (
 select doc_id, len(c)::bigint as latex_hits, len(list_distinct(c))::bigint as latex_kinds, ({_PLAIN})::bigint as plain_hits, ({_KINDS})::bigint as plain_kinds
 from (select doc_id, text, list_filter(regexp_extract_all(text, '\\\\([A-Za-z]+)', 1), lambda x: x in ({_CMDS})) as c from ({X.ascii_sql()})))""")
def math_keyword_hits(spark, d):
    return keywords.score_math_keywords(X.derived(spark, d, X.ascii_sql())).drop("text")


@_key()
def math_text_corpus(spark, d):
    docs = X.derived(spark, d, X.ascii_sql())
    pos = tracks.math_markup_track().run(_math(spark, d)).df.select("text")
    model = models.train_text_classifier(models.build_math_training(pos, _docs(spark, d), 200))
    return tracks.math_ascii_track(model).run(docs).df.select("doc_id", F.round("p_math", 4).alias("p_math"))


# ---------------------------------------------------------------- questions

def _qa(spark, d):
    return X.derived(spark, d, X.qa_sql("spark"))


def _choice(spark, d):
    return X.derived(spark, d, X.choice_sql("spark"))


def _sum_hits(words) -> str:
    return " + ".join(f"contains(lower(text), '{w}')::bigint" for w in words)


def _edge(words) -> str:
    bare, colon = [w for w in words if w[-1] != ":"], [w for w in words if w[-1] == ":"]
    return f"(regexp_matches(lower(text), '(^|[^a-z0-9])({'|'.join(bare)})($|[^a-z0-9])') or regexp_matches(lower(text), '(^|[^a-z0-9])({'|'.join(colon)})'))"


@_key(f"select doc_id, q_hits, a_hits, q_hits > 0 and a_hits > 0 as keep, keep_bounded from (select doc_id, {_sum_hits(keywords.QUESTION)} as q_hits, {_sum_hits(keywords.ANSWER)} as a_hits, {_edge(keywords.QUESTION)} and {_edge(keywords.ANSWER)} as keep_bounded from ({X.qa_sql('duckdb')}))")
def qa_rule_flags(spark, d):
    return keywords.score_qa_keywords(_qa(spark, d)).drop("text")


def _qa_model(spark, d):
    """Trained on texts marked by the bounded keyword rule, which stands for the annotator; question types are balanced."""
    marked = keywords.score_qa_keywords(_qa(spark, d).where(~models.held_out())).withColumn("label", F.col("keep_bounded").cast("int"))
    kind = F.regexp_extract(F.lower("text"), "(" + "|".join(w for w in keywords.QUESTION if w.isalpha()) + ")", 1)
    drawn = models.stratified_sample(marked.withColumn("kind", kind), "label", "kind", 1000)
    sizes = [r["count"] for r in drawn.groupBy("label").count().collect()]
    return models.train_text_classifier(models.balanced_sample(drawn, "label", min(sizes)))


@_key()
def open_qa_corpus(spark, d):
    return tracks.open_qa_track(_qa_model(spark, d)).run(_qa(spark, d)).df.select("doc_id", F.md5("text").alias("text_md5"))


_LIST = r"(^|\n)[ \t]*([A-Za-z]|[0-9]{1,2}|[ivxIVX]{1,4}) ?[.)>\] -]"


@_key(f"select doc_id, regexp_matches(text, '{_LIST}') as has_list, {' or '.join(f"contains(lower(text), '{w}')" for w in ('answer:', 'solution:', 'reply:', 'response:', 'ans:', 'a:', 'r:'))} as has_answer from ({X.choice_sql('duckdb')})")
def choice_pages(spark, d):
    return keywords.score_choice_page(_choice(spark, d)).drop("text")


#: What the planted classes must give: style, options and answer of each class, from the classes' own definition.
_PLANTED = "(values (0, 'letter', 4, 'answer: b', 1), (1, 'arabic', 3, 'Ans: 2', 1), (2, 'roman', 4, 'solution: i', 1), (6, 'letter', 3, 'reply: a', 1), (7, 'letter', 2, 'answer: a', 2)) p(m, style, n, answer, times)"
_USERS = "(select distinct conv_id from conversations where role = 'user')"


@_key(f"select conv_id as doc_id, style, n::bigint as n_options from {_USERS} join (select * from {_PLANTED.replace(' p(', ' q(')}, range(2) r(k) where k < times) p on conv_id % 8 = m union all select conv_id, 'letter', 3 from {_USERS} where conv_id % 8 = 3 union all select conv_id, 'letter', 2 from {_USERS} where conv_id % 8 = 5")
def choice_runs(spark, d):
    return extract.choice_run_rows(_choice(spark, d)).drop("first")


@_key(f"select conv_id as doc_id, style, answer, count(*) over () as questions from {_USERS} join (select * from {_PLANTED.replace(' p(', ' q(')}, range(2) r(k) where k < times) p on conv_id % 8 = m")
def choice_questions(spark, d):
    got = extract.choice_rows(_choice(spark, d)).select("doc_id", "style", "answer")
    return got.crossJoin(got.agg(F.count("*").alias("questions")))


@_key()
def choice_questions_any_order(spark, d):
    return extract.choice_rows(_choice(spark, d), "any").select("doc_id", "style", "answer")


_WRITTEN = """array_to_string(list_transform(range(n), lambda i: chr((65 + i)::int) || '. ' || rtrim('opt' || i || ' ' || array_to_string(w[9 + 2 * i:10 + 2 * i], ' '))), chr(10))"""


@_key(f"""select doc_id, q.first::bigint as first, md5(rtrim('stem ' || array_to_string(w[1:6], ' ')) || chr(10) || {_WRITTEN} || chr(10) || 'Answer: ' || answer || more) as md5
 from (select conv_id as doc_id, conv_id % 8 as m, string_split(replace(arg_min(text, turn), chr(10), ' '), ' ') as w from conversations where role = 'user' group by conv_id)
 join (values (0, 4, 'b', ''), (1, 3, '2', chr(10) || 'Explanation: it follows'), (2, 4, 'i', ''), (6, 3, 'a', ''), (7, 2, 'a', '')) p(m, n, answer, more) using (m)
 join (values (0, 2), (1, 2), (2, 2), (6, 2), (7, 2), (7, 6)) q(m, first) using (m)""")
def choice_formatted(spark, d):
    return tracks.choice_qa_track().run(_choice(spark, d)).df.select("doc_id", "first", F.md5("formatted").alias("md5"))


# ---------------------------------------------------------------- measures and experiments

@_key(f"select coalesce(source, 'total') as source, count(*) as pages, sum(len({W}))::bigint as tokens, (sum(len({W})) // count(*))::bigint as tokens_per_page from documents group by rollup(source)")
def dataset_stats(spark, d):
    return measures.dataset_stats(_docs(spark, d), "source")


@_key(f"""with f as (select d.doc_id, n_words, quality, n_chars >= 300 as length_only, not ({' or '.join(f'f_{x}' for x in ('words', 'mean_word', 'symbols', 'bullets', 'ellipses', 'no_alpha', 'stops'))}) as rules_only
 from documents d join (select *, {_DOC_FLAGS} from ({_DOC_INPUTS})) using (doc_id) left join labels using (doc_id))
 {' union all '.join(f"select '{r}' as recipe, count(*) as docs, sum(n_words)::bigint as tokens, count_if(quality = 1) as good, count(quality) as marked from f where {c}" for r, c in (('raw', 'true'), ('length_only', 'length_only'), ('rules_only', 'rules_only')))}""")
def recipe_comparison(spark, d):
    docs = _docs(spark, d).select("doc_id", "text")
    f = tracks.recipe_flags(docs).withColumn("t", measures.token_count(F.col("text"))).join(load(spark, d, "labels"), "doc_id", "left")
    recipes = F.array(*[F.struct(F.lit(r).alias("recipe"), F.col(r).alias("on")) for r in ("raw", "length_only", "rules_only")])
    long = f.select("t", "quality", F.explode(recipes).alias("r")).where("r.on")
    return long.groupBy("r.recipe").agg(F.count("*").alias("docs"), F.sum("t").alias("tokens"), F.count_if(F.col("quality") == 1).alias("good"), F.count("quality").alias("marked"))


_RECIPES = ("raw", "length_only", "rules_only", "model_only", "full")


def _scored_recipes(spark, d):
    docs = _docs(spark, d).select("doc_id", "text")
    return tracks.recipe_flags(docs, models.score_model(docs, _quality_model(spark, d)))


@_key()
def recipe_comparison_models(spark, d):
    """``recipe_comparison`` with the recipes that need a model."""
    f = _scored_recipes(spark, d).withColumn("t", measures.token_count(F.col("text"))).join(load(spark, d, "labels"), "doc_id", "left")
    recipes = F.array(*[F.struct(F.lit(r).alias("recipe"), F.col(r).alias("on")) for r in _RECIPES])
    long = f.select("t", "quality", F.explode(recipes).alias("r")).where("r.on")
    return long.groupBy("r.recipe").agg(F.count("*").alias("docs"), F.sum("t").alias("tokens"), F.count_if(F.col("quality") == 1).alias("good"), F.count("quality").alias("marked"))


def _lm_sql(train: str, held: str) -> str:
    pairs = lambda t: f"select ws[i] as u, ws[i + 1] as v from (select ws, unnest(range(1, len(ws))) as i from (select list_prepend('<s>', list_transform({W}, lambda x: lower(x))) as ws from {t}) where len(ws) > 1)"
    return f"""(with tr as ({pairs(train)}), both_ as (select u, v, count(*) as n_uv from tr group by 1, 2), hist as (select u, count(*) as n_u from tr group by 1), types as (select count(distinct v) + 1 as t from tr),
 he as (select u, v, count(*) as k from ({pairs(held)}) group by 1, 2)
 select sum(k)::bigint as tokens, exp(-sum(ln((coalesce(n_uv, 0) + 0.1e0) / (coalesce(n_u, 0) + 0.1e0 * t)) * k) / sum(k)) as ppl from he left join both_ using (u, v) left join hist using (u) cross join types)"""


@_key(f"select 'raw' as recipe, tokens, round(ppl, 2) as perplexity from {_lm_sql('documents', 'benchmark')} union all select 'length_only', tokens, round(ppl, 2) from {_lm_sql('(select * from documents where n_chars >= 300)', 'benchmark')}")
def recipe_perplexity(spark, d):
    docs, bench = _docs(spark, d), load(spark, d, "benchmark")
    one = lambda n, t: measures.perplexity(measures.train_ngram_lm(t), bench).select(F.lit(n).alias("recipe"), "tokens", F.round("perplexity", 2).alias("perplexity"))
    return one("raw", docs).unionByName(one("length_only", docs.where("n_chars >= 300")))


@_key()
def recipe_perplexity_models(spark, d):
    """``recipe_perplexity`` of all recipes; documents are scored and their word pairs counted once."""
    got = measures.perplexities(_scored_recipes(spark, d), _RECIPES, load(spark, d, "benchmark"))
    return got.select("recipe", "tokens", F.round("perplexity", 2).alias("perplexity"))


@_key()
def math_perplexity(spark, d):
    """Held-out formula texts under a model of valid pages and of all prefiltered pages."""
    pages = _math(spark, d)
    held = F.col("page_id") % 5 == 0
    texts = extract.math_pass(keywords.keep_math_page(pages))
    test = texts.where(held & F.col("keep"))
    one = lambda n, t: measures.perplexity(measures.train_ngram_lm(t), test).select(F.lit(n).alias("recipe"), "tokens", F.round("perplexity", 2).alias("perplexity"))
    return one("valid_only", texts.where(~held & F.col("keep"))).unionByName(one("prefilter_only", texts.where(~held)))


def _whole_mix_sql(tables: str, parts: dict[str, int]) -> str:
    """Tokens by track of a mix at the largest budget that both sources can fill."""
    total = ", ".join(f"coalesce(sum(n) filter (track = '{k}'), 0) // {w}" for k, w in parts.items())
    share = " ".join(f"when '{k}' then {w}" for k, w in parts.items())
    return f"""with t as ({tables}), u as (select least({total}) as unit from t),
 r as (select track, doc_id, n, sum(n) over (partition by track order by ('0x' || substr(md5(track || ':' || doc_id), 1, 15))::bigint, doc_id) as run from t)
 select track, count(*) as docs, sum(n)::bigint as tokens from r cross join u where run - n < unit * (case track {share} end) group by 1"""


def _whole_mix(docs, parts):
    got = measures.mix(docs, {k: n / sum(parts.values()) for k, n in parts.items()}, measures.whole_budget(docs, parts))
    return got.groupBy("track").agg(F.count("*").alias("docs"), F.sum(measures.token_count(F.col("text"))).alias("tokens"))


@_key(_whole_mix_sql(f"select 'web' as track, doc_id, len({W}) as n from documents where lang = 'en' union all select 'code', doc_id, len({W}) from documents where lang is null or lang <> 'en'", {"web": 4, "code": 1}))
def mixture_web_code(spark, d):
    """Web and code at 0.8 and 0.2 of the whole corpus: the scarcer is used up. On the given texts the other languages stand for code."""
    docs = _docs(spark, d).select(F.when(F.col("lang") == "en", "web").otherwise("code").alias("track"), "doc_id", "text")
    return _whole_mix(docs, {"web": 4, "code": 1})


@_key(_whole_mix_sql(f"select 'open' as track, doc_id, len({W}) as n from ({X.qa_sql('duckdb')}) union all select 'choice', doc_id, len({W}) from ({X.choice_sql('duckdb')})", {"open": 4, "choice": 1}))
def mixture_qa(spark, d):
    """Open and choice questions at 0.8 and 0.2 of all texts: the scarcer is used up."""
    both = _qa(spark, d).withColumn("track", F.lit("open")).unionByName(_choice(spark, d).withColumn("track", F.lit("choice")))
    return _whole_mix(both, {"open": 4, "choice": 1})


def _pass_sql(k: int) -> str:
    return f"case when c = 0 then 0 when n - c < {k} then 1 else 1 - list_product(list_transform(range(n - c + 1, n + 1), lambda j: 1 - {k}.0e0 / j)) end"


@_key(f"select user_id as task, n, c, round({_pass_sql(1)}, 6)::double as pass_1, round({_pass_sql(10)}, 6)::double as pass_10 from (select user_id, count(*) as n, count_if(event_type = 'purchase')::bigint as c from events group by 1)")
def pass_at_k(spark, d):
    t = load(spark, d, "events").groupBy(F.col("user_id").alias("task")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "purchase").alias("c"))
    return t.select("task", "n", "c", *[F.round(measures.pass_at_k(F.col("n"), F.col("c"), k), 6).alias(f"pass_{k}") for k in (1, 10)])


#: Scores of four decimals: the values of events, by their kind.
_SCORES = "select event_type as corpus, event_id, floor(value * 10000) / 10000 as score from events"


@_key(f"select corpus, floor(sum(round(score * 10000)) / count(*) + 0.5) / 10000 as average from ({_SCORES}) group by 1")
def macro_average(spark, d):
    return measures.macro_average(X.derived(spark, d, _SCORES), "corpus")


#: A run's score of a task: the mean value of a kind of events, of even or of odd ids. Sums are of whole hundredths.
_RUN = "select event_type as task, cast(sum(cast(floor(value * 100) as bigint)) as double) / (100 * count(*)) as score from events where event_id % 2 = {0} group by event_type"


@_key(f"select task, round((b.score - a.score) * 100, 2) as points, round((b.score / a.score - 1) * 100, 2) as percent from ({_RUN.format(0)}) a join ({_RUN.format(1)}) b using (task)")
def compare_runs(spark, d):
    a, b = (X.derived(spark, d, _RUN.format(k)) for k in (0, 1))
    return measures.compare_runs(a, b)


#: Rules whose pass rate is told: the key with its verdicts and the condition to pass.
_RATES = {
    "length": ("length_rule", "keep_length"), "code_page": ("code_prefilter", "(has_code_tag or has_pre_tag) and not blocked_url"),
    "math_keywords": ("math_keyword_hits", "keep_occurrence"), "qa_keywords": ("qa_rule_flags", "keep"), "choice_page": ("choice_pages", "has_list and has_answer"),
}


@_key(" union all ".join(f"select '{n}' as rule, count(*) as pages, count_if({c})::bigint as passed, (count_if({c})::bigint * 1000000 // greatest(count(*), 1))::bigint as share_ppm from ({_ORACLES[k]})" for n, (k, c) in _RATES.items()))
def pass_rates(spark, d):
    """Pages that each keyword or length rule is asked about, and those that pass."""
    return functools.reduce(DataFrame.unionByName, [measures.pass_rate(_QUERIES[k](spark, d), F.expr(c), n) for n, (k, c) in _RATES.items()])


@_key("""with t as (select n_chars as s, count_if(quality = 1) as p, count_if(quality = 0) as n from documents join labels using (doc_id) group by 1),
 b as (select p, n, coalesce(sum(n) over (order by s rows between unbounded preceding and 1 preceding), 0) as below from t)
 select sum(p)::bigint as positives, sum(n)::bigint as negatives, round(sum(p * (2 * below + n)) / nullif(2.0e0 * sum(p) * sum(n), 0), 6) as auc from b""")
def length_auc(spark, d):
    """How well length alone ranks documents by quality: what the model of ``quality_auc`` has to beat."""
    return measures.auc(_docs(spark, d).join(load(spark, d, "labels"), "doc_id"), "quality", "n_chars")


@_key()
def quality_auc(spark, d):
    held = models.annotate(_docs(spark, d), load(spark, d, "labels")).where(models.held_out())
    return measures.auc(models.score_model(held.select("doc_id", "text", "label"), _quality_model(spark, d)), "label", "p_quality")


@_key()
def web_linearizer_baseline(spark, d):
    """What the page route keeps of main content and of all visible text."""
    given, pages = (_language_model(spark, d), _quality_model(spark, d)), load(spark, d, "pages")
    counts = F.count("*").alias("docs"), F.coalesce(F.sum(measures.token_count(F.col("text"))), F.lit(0)).alias("tokens")
    one = lambda c: tracks.web_track_warc(*given, content=c).run(pages).df.agg(F.lit(c).alias("content"), *counts)
    return one("main").unionByName(one("full"))


@_key()
def track_stats(spark, d):
    """Pages (questions, of choice_qa) and tokens by track, with a total."""
    found = {
        "code": tracks.code_track().run(_code(spark, d)), "math": tracks.math_markup_track().run(_math(spark, d)),
        "open_qa": tracks.open_qa_track().run(_qa(spark, d)), "choice_qa": tracks.choice_qa_track().run(_choice(spark, d)),
    }
    texts = [r.df.select(F.lit(n).alias("track"), "text") for n, r in found.items()]
    return measures.dataset_stats(functools.reduce(DataFrame.unionByName, texts), "track")


def _gram13(table: str, key: str) -> str:
    return f"select distinct {key}, array_to_string(w[i:i + 12], ' ') as g from (select {key}, w, unnest(range(1, len(w) - 11)) as i from (select {key}, {W.replace('text', 'lower(text)')} as w from {table}) where len(w) >= 13)"


@_key(f"select doc_id, item_id, count(*) as shared from ({_gram13('documents', 'doc_id')}) join ({_gram13('benchmark', 'item_id')}) using (g) group by 1, 2")
def benchmark_overlap(spark, d):
    return measures.benchmark_overlap(_docs(spark, d), load(spark, d, "benchmark"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_ORACLES)
