"""Cost and accuracy measures: statistics, funnels, pass@k, averages, perplexity, mixtures, contamination."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions import text as T
from ..functions.text import hash60
from .minhash import checkpointed


def token_count(text: Column) -> Column:
    """Tokens of a text: words, a declared proxy for an unnamed subword tokenizer."""
    return F.size(T.words(F.coalesce(text, F.lit("")))).cast("long")


def dataset_stats(df: DataFrame, by: str) -> DataFrame:
    """Pages, tokens and tokens per page by ``by`` with a total row."""
    t = df.select(by, token_count(F.col("text")).alias("t"))
    out = t.rollup(by).agg(F.count("*").alias("pages"), F.sum("t").alias("tokens"))
    return out.select(F.coalesce(by, F.lit("total")).alias(by), "pages", "tokens", F.floor(F.col("tokens") / F.col("pages")).cast("long").alias("tokens_per_page"))


def funnel(verdicts: DataFrame, stages: list[str], tokens: str = "n_words") -> DataFrame:
    """Documents and tokens left after each stage, in one aggregate over per-row verdicts."""
    alive = F.lit(True)
    parts = [F.struct(F.lit(0).alias("step"), F.lit("input").alias("stage"), F.count("*").alias("docs"), F.sum(tokens).alias("tokens"))]
    for i, s in enumerate(stages):
        alive = alive & F.col(s)
        parts.append(F.struct(F.lit(i + 1).alias("step"), F.lit(s).alias("stage"), F.count_if(alive).alias("docs"), F.coalesce(F.sum(F.when(alive, F.col(tokens))), F.lit(0)).alias("tokens")))
    out = verdicts.agg(F.array(*parts).alias("rows")).select(F.explode("rows").alias("r")).select("r.*")
    first = F.first("tokens").over(Window.partitionBy(F.lit(0)).orderBy("step"))  # as many rows as stages
    return out.withColumn("removed_ppm", F.floor((first - F.col("tokens")) * 1_000_000 / F.greatest(first, F.lit(1))).cast("long"))


def rule_report(flags: DataFrame) -> DataFrame:
    """Documents hit by each ``f_*`` column and their share in millionths."""
    names = [c for c in flags.columns if c.startswith("f_")]
    counts = flags.agg(F.count("*").alias("docs"), *[F.count_if(c).alias(c) for c in names])
    long = counts.unpivot(["docs"], names, "rule", "hits")
    return long.select("rule", "hits", F.floor(F.col("hits") * 1_000_000 / F.greatest("docs", F.lit(1))).cast("long").alias("share_ppm"))


def pass_at_k(n: Column, c: Column, k: int) -> Column:
    """Unbiased estimate that one of ``k`` draws out of ``n`` attempts with ``c`` right ones is right."""
    fail = F.aggregate(F.sequence(n - c + 1, n), F.lit(1.0), lambda s, j: s * (1 - F.lit(float(k)) / j))
    return F.when(c == 0, 0.0).when(n - c < k, 1.0).otherwise(1 - fail)


def pass_rate(flags: DataFrame, keep: Column, rule: str) -> DataFrame:
    """One row: pages that a rule was asked about, those that it keeps, and their share in millionths."""
    counts = flags.agg(F.lit(rule).alias("rule"), F.count("*").alias("pages"), F.count_if(keep).alias("passed"))
    return counts.withColumn("share_ppm", F.expr("(passed * 1000000) div greatest(pages, 1)"))


def auc(df: DataFrame, label: str, score: str, decimals: int = 4) -> DataFrame:
    """One row ``(positives, negatives, auc)``: the chance that a row of label 1 outranks one of label 0, ties half.

    Rows are counted by score first, so the running sum is over as many rows as
    there are scores of ``decimals`` decimals.
    """
    y = F.col(label)
    t = df.groupBy(F.round(score, decimals).alias("s")).agg(F.count_if(y == 1).alias("p"), F.count_if(y == 0).alias("n"))
    below = F.sum("n").over(Window.partitionBy(F.lit(0)).orderBy("s").rowsBetween(Window.unboundedPreceding, -1))
    t = t.withColumn("won", F.col("p") * (2 * F.coalesce(below, F.lit(0)) + F.col("n")))
    both = F.nullif(2.0 * F.sum("p") * F.sum("n"), F.lit(0.0))
    return t.agg(F.sum("p").alias("positives"), F.sum("n").alias("negatives"), F.round(F.sum("won") / both, 6).alias("auc"))


def macro_average(scores: DataFrame, by: str, score: str = "score") -> DataFrame:
    """Mean of scores that have four decimals, rounded half up to four."""
    whole = F.sum(F.round(F.col(score) * 10_000)) / F.count("*")
    return scores.groupBy(by).agg((F.floor(whole + 0.5) / 10_000).alias("average"))


def compare_runs(a: DataFrame, b: DataFrame, on: str = "task") -> DataFrame:
    """Absolute and relative difference of two runs, in hundredths of points and per cent."""
    j = a.select(on, F.col("score").alias("x")).join(b.select(on, F.col("score").alias("y")), on)
    return j.select(on, F.round((F.col("y") - F.col("x")) * 100, 2).alias("points"), F.round((F.col("y") / F.col("x") - 1) * 100, 2).alias("percent"))


def with_metrics(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """Count rows while a query runs, without a second pass."""
    seen = Observation(name)
    return df.observe(seen, F.count("*").alias("rows")), seen


def mix(df: DataFrame, weights: dict[str, float], budget: int, by: str = "track", id: str = "doc_id") -> DataFrame:
    """Documents of each source in hash order until its share of the token budget is met.

    Running sums over a hot source would meet in one task: documents are first
    summed by 256 hash ranges, and only the range where the budget ends needs
    running sums of its own.
    """
    h = hash60(F.concat_ws(":", by, F.col(id).cast("string")))
    t = df.select("*", token_count(F.col("text")).alias("_t"), h.alias("_h")).withColumn("_slot", F.shiftright("_h", 52))
    share = F.create_map(*[x for k, w in weights.items() for x in (F.lit(k), F.lit(math.floor(budget * w + 0.5)))])
    slots = t.groupBy(by, "_slot").agg(F.sum("_t").alias("_n"))
    before = F.sum("_n").over(Window.partitionBy(by).orderBy("_slot").rowsBetween(Window.unboundedPreceding, -1))
    slots = slots.select(by, "_slot", F.coalesce(before, F.lit(0)).alias("_before"))
    run = F.sum("_t").over(Window.partitionBy(by, "_slot").orderBy("_h", id).rowsBetween(Window.unboundedPreceding, 0))
    near = t.join(slots, [by, "_slot"]).where(F.col("_before") < F.element_at(share, F.col(by)))
    taken = near.withColumn("_run", F.col("_before") + run).where(F.col("_run") - F.col("_t") < F.element_at(share, F.col(by)))
    return taken.drop("_t", "_h", "_slot", "_before", "_run")


def whole_budget(df: DataFrame, parts: dict[str, int], by: str = "track") -> int:
    """Largest token budget that every source can fill with its whole parts of it; one total a source is collected."""
    totals = {r[0]: r[1] for r in df.groupBy(by).agg(F.sum(token_count(F.col("text")))).collect()}
    return sum(parts.values()) * min((totals.get(k) or 0) // n for k, n in parts.items())


def _bigrams(df: DataFrame, *keep: str) -> DataFrame:
    w = F.concat(F.array(F.lit("<s>")), F.transform(T.words(F.coalesce("text", F.lit(""))), lambda x: F.lower(x)))
    t = df.select(*keep, w.alias("w")).where(F.size("w") > 1)
    pairs = F.transform(F.sequence(F.lit(1), F.size("w") - 1), lambda i: F.struct(F.element_at("w", i).alias("u"), F.element_at("w", i + 1).alias("v")))
    return t.select(*keep, F.explode(pairs).alias("p")).select(*keep, "p.u", "p.v")


def train_ngram_lm(df: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Bigram counts, history counts and the vocabulary size of a corpus."""
    pairs = _bigrams(df)
    both = pairs.groupBy("u", "v").agg(F.count("*").alias("n_uv"))
    hist = pairs.groupBy("u").agg(F.count("*").alias("n_u"))
    vocab = pairs.select("v").distinct().agg((F.count("*") + 1).alias("types"))
    return both, hist, vocab


def perplexity(lm: tuple[DataFrame, DataFrame, DataFrame], held: DataFrame, alpha: float = 0.1) -> DataFrame:
    """One row ``(tokens, perplexity)``: add-alpha bigrams, scored by joins on counts of distinct held-out pairs."""
    both, hist, vocab = lm
    seen = _bigrams(held).groupBy("u", "v").agg(F.count("*").alias("k"))
    j = seen.join(both, ["u", "v"], "left").join(hist, "u", "left").crossJoin(vocab)
    logp = F.log((F.coalesce("n_uv", F.lit(0)) + alpha) / (F.coalesce("n_u", F.lit(0)) + alpha * F.col("types")))
    return j.agg(F.sum("k").alias("tokens"), F.exp(-F.sum(logp * F.col("k")) / F.sum("k")).alias("perplexity"))


def perplexities(df: DataFrame, recipes: tuple[str, ...], held: DataFrame, alpha: float = 0.1) -> DataFrame:
    """Rows ``(recipe, tokens, perplexity)``: ``perplexity`` of the texts that each flag column marks, counted in one pass over all of them."""
    flags = _bigrams(df, *recipes).groupBy("u", "v").agg(*[F.count_if(r).alias(f"n_{r}") for r in recipes])
    both = checkpointed(flags.where(" or ".join(f"n_{r} > 0" for r in recipes)))
    hist = both.groupBy("u").agg(*[F.sum(f"n_{r}").alias(f"h_{r}") for r in recipes])
    vocab = both.groupBy("v").agg(*[F.max(F.col(f"n_{r}") > 0).alias(r) for r in recipes]).agg(*[(F.count_if(r) + 1).alias(f"t_{r}") for r in recipes])
    seen = _bigrams(held).groupBy("u", "v").agg(F.count("*").alias("k"))
    j = seen.join(both, ["u", "v"], "left").join(hist, "u", "left").crossJoin(vocab)
    logp = lambda r: F.log((F.coalesce(f"n_{r}", F.lit(0)) + alpha) / (F.coalesce(f"h_{r}", F.lit(0)) + alpha * F.col(f"t_{r}")))
    told = j.agg(F.array(*[F.struct(F.lit(r).alias("recipe"), F.sum("k").alias("tokens"), F.exp(-F.sum(logp(r) * F.col("k")) / F.sum("k")).alias("perplexity")) for r in recipes]).alias("x"))
    return told.select(F.explode("x").alias("x")).select("x.*")


def benchmark_overlap(docs: DataFrame, bench: DataFrame, n: int = 13) -> DataFrame:
    """Rows ``(doc_id, item_id, shared)``: distinct word n-grams a document shares with a benchmark item, by hash join."""

    def grams(df: DataFrame, key: str) -> DataFrame:
        w = df.select(key, T.words(F.lower(F.coalesce("text", F.lit("")))).alias("w")).where(F.size("w") >= n)
        windows = F.transform(F.sequence(F.lit(1), F.size("w") - n + 1), lambda i: F.md5(F.array_join(F.slice("w", i, n), " ")))
        return w.select(key, F.explode(F.array_distinct(windows)).alias("h"))

    return grams(docs, "doc_id").join(grams(bench, "item_id"), "h").groupBy("doc_id", "item_id").agg(F.count("*").alias("shared"))
