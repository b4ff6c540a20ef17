"""Tracks: ordered extraction and filtering stages per kind of data, and recipes to compare them with."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import extract, keywords, minhash, models, paragraphs, rules
from ..operators.measures import token_count

Step = Callable[[DataFrame], DataFrame]


@dataclass(frozen=True)
class Stage:
    """One step; ``kind`` is ``extract`` or ``filter``."""

    name: str
    kind: str
    step: Step


@dataclass
class TrackResult:
    df: DataFrame
    after: list[tuple[str, DataFrame]] = field(default_factory=list)

    def funnel(self) -> DataFrame:
        """Rows and tokens after each stage (one job a stage; the verdict form in ``measures.funnel`` needs one in all)."""
        parts = [
            d.agg(F.lit(i).alias("step"), F.lit(n).alias("stage"), F.count("*").alias("docs"), F.coalesce(F.sum(token_count(F.col("text"))), F.lit(0)).alias("tokens"))
            for i, (n, d) in enumerate(self.after)
            if "text" in d.columns
        ]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


@dataclass(frozen=True)
class Track:
    """A lazy chain: nothing runs until the result is read."""

    name: str
    stages: tuple[Stage, ...]

    def run(self, df: DataFrame) -> TrackResult:
        result = TrackResult(df, [("input", df)])
        for s in self.stages:
            result.df = s.step(result.df)
            result.after.append((s.name, result.df))
        return result


def _lsh(df: DataFrame) -> DataFrame:
    gone = minhash.dedup_lsh(minhash.lsh_bands(minhash.minhash_signatures(df)))
    return df.join(gone.select("doc_id"), "doc_id", "left_anti")


def _quality(model, threshold: float = 0.5) -> Step:
    return lambda d: models.score_model(d, model).where(F.col("p_quality") >= threshold)


def _language(model) -> Step:
    return lambda d: models.keep_language(models.score_language(d, model))


def _sentences(df: DataFrame) -> DataFrame:
    out = rules.apply_sentence_rules(df).where("not f_sentences")
    return out.select(*[c for c in df.columns if c != "text"], F.col("text_clean").alias("text"))


def _only(df: DataFrame, flagged: DataFrame) -> DataFrame:
    return flagged.where(~rules.any_flag(flagged.columns)).select(*df.columns)


def web_track_wet(lang_model, quality_model=None) -> Track:
    """Plain-text route: snapshot-wide paragraph dedup, language, length, model, LSH."""

    def dedup(d: DataFrame) -> DataFrame:
        got = paragraphs.dedup_paragraphs(d.withColumn("snapshot", paragraphs.snapshot(F.col("source"))), scope=("snapshot",))
        return got.select("doc_id", "lang", "source", F.col("text_dedup").alias("text"))

    stages = [
        Stage("paragraph_dedup", "extract", dedup),
        Stage("language", "filter", _language(lang_model)),
        Stage("length", "filter", lambda d: d.where(F.length("text") >= 300)),
    ]
    if quality_model is not None:
        stages.append(Stage("model", "filter", _quality(quality_model)))
    return Track("web_wet", (*stages, Stage("lsh", "filter", _lsh)))


def web_track_warc(lang_model, quality_model=None, content: str = "main") -> Track:
    """Page route: main content, language, repetition and document rules, sentence rules, model, LSH.

    With ``content="full"`` all visible text takes the place of the main content.
    """
    take = extract.extract_main_content if content == "main" else extract.linearize_html
    stages = [
        Stage(f"{content}_content", "extract", lambda d: take(d.select(F.col("page_id").alias("doc_id"), "url", "html")).select("doc_id", "url", "text")),
        Stage("language", "filter", _language(lang_model)),
        Stage("repetition", "filter", lambda d: _only(d, rules.score_repetition(d))),
        Stage("document_rules", "filter", lambda d: _only(d, rules.score_document_rules(d))),
        Stage("sentence_rules", "filter", _sentences),
    ]
    if quality_model is not None:
        stages.append(Stage("model", "filter", _quality(quality_model)))
    return Track("web_warc", (*stages, Stage("lsh", "filter", _lsh)))


def merge_formats(wet: DataFrame, warc: DataFrame) -> DataFrame:
    """Both routes under one schema, with the format kept for accounts."""
    pick = lambda d, f: d.select("doc_id", "text").withColumn("format", F.lit(f))
    return pick(wet, "wet").unionByName(pick(warc, "warc"))


def code_track() -> Track:
    return Track("code", (Stage("prefilter", "filter", keywords.keep_code_page), Stage("snippets", "extract", extract.code_pass), Stage("has_code", "filter", lambda d: d.where("has_code"))))


def math_markup_track(on_error: str = "drop_page") -> Track:
    return Track("math_markup", (Stage("prefilter", "filter", keywords.keep_math_page), Stage("formulas", "extract", lambda d: extract.math_pass(d, on_error)), Stage("valid", "filter", lambda d: d.where("keep"))))


def math_ascii_track(model=None, threshold: float = 0.5) -> Track:
    """Plain-text math: keyword rule, then the text model. Takes texts; pages go through ``extract_main_content`` first."""
    stages = [Stage("keywords", "filter", lambda d: keywords.score_math_keywords(d).where("keep_occurrence").select(*d.columns))]
    if model is not None:
        stages.append(Stage("model", "filter", lambda d: models.score_model(d, model, "p_math").where(F.col("p_math") >= threshold)))
    return Track("math_ascii", tuple(stages))


def open_qa_track(model=None, threshold: float = 0.5) -> Track:
    def dedup(d: DataFrame) -> DataFrame:
        return paragraphs.dedup_paragraphs(d).select("doc_id", F.col("text_dedup").alias("text"))

    stages = [Stage("paragraph_dedup", "extract", dedup), Stage("keywords", "filter", lambda d: keywords.score_qa_keywords(d).where("keep").select(*d.columns))]
    if model is not None:
        stages.append(Stage("model", "filter", lambda d: models.score_model(d, model, "p_qa").where(F.col("p_qa") >= threshold)))
    return Track("open_qa", tuple(stages))


def choice_qa_track(answer_position: str = "after") -> Track:
    return Track(
        "choice_qa",
        (
            Stage("choice_page", "filter", lambda d: keywords.score_choice_page(d).where("has_list and has_answer").select(*d.columns)),
            Stage("questions", "extract", lambda d: extract.choice_rows(d, answer_position).withColumn("text", F.col("formatted"))),
        ),
    )


@dataclass(frozen=True)
class DomainSpec:
    """A new domain: what a page must contain, how to find and check its parts, how to write it out."""

    name: str
    keywords: tuple[str, ...]
    locate: Step
    verify: Step
    column: str = "html"

    def track(self) -> Track:
        prefilter = Stage("prefilter", "filter", lambda d: d.where(keywords.any_keyword(F.col(self.column), self.keywords)))
        return Track(self.name, (prefilter, Stage("locate", "extract", self.locate), Stage("verify", "filter", self.verify)))


def recipe_flags(docs: DataFrame, scored: DataFrame | None = None) -> DataFrame:
    """One row per document with the verdict of each comparison recipe: raw, length only, rules only, model only, both."""
    flagged = rules.score_document_rules(docs)
    out = flagged.select(*docs.columns, F.lit(True).alias("raw"), (F.length("text") >= 300).alias("length_only"), (~rules.any_flag(flagged.columns)).alias("rules_only"))
    if scored is not None:
        out = out.join(scored.select("doc_id", (F.col("p_quality") >= 0.5).alias("model_only")), "doc_id").withColumn("full", F.col("rules_only") & F.col("model_only"))
    return out
