"""The registered query of each operator, with production parameters, over its whole table; and SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from refinery.llm import chat, decontaminate, html_text, jaccard_join, language, lm_score, mixing, quality, token_counts, url_filter
from refinery.llm.common import read


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.similarity_classes(read(spark, sf_dir, "documents"), every=True)


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(read(spark, sf_dir, "pages"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select("page_id", "url")
    return url_filter.url_verdicts(pages, url_filter.tracker_list(pages)).select("page_id", "host", "path", "rule", "verdict")


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mixing.schedule(read(spark, sf_dir, "documents"))
    rows = rows.withColumn("position", F.get("copies", F.lit(0))["position"])  # null where nothing is taken
    return mixing.range_sorted(rows, "position").select("doc_id", "size", "source_size", "target", "taken")


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(read(spark, sf_dir, "documents"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.counts_after_edits(read(spark, sf_dir, "documents"))


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = decontaminate.contaminated(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))
    return rows.withColumns({"item_id": F.coalesce("item_id", F.lit(-1)), "start": F.coalesce("start", F.lit(-1)), "similarity": F.coalesce("similarity", F.lit(0.0))})


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return chat.digests(chat.format_turns(turns.unionByName(chat.fixture_turns(spark)))).drop("n_escaped")


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.assess(read(spark, sf_dir, "documents")).drop("n_bad_lines", "lost_words")


def op10_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_score.lm_scores(read(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_jaccard_join, op2_html_text, op3_url_filter, op4_mixing, op5_language, op6_token_counts, op7_decontaminate, op8_chat_format, op9_quality_rules, op10_lm_score)
}

ORACLES = {
    "op3_url_filter": url_filter.ORACLE,
    "op4_mixing": mixing.ORACLE,
    "op7_decontaminate": decontaminate.ORACLE,
    "op8_chat_format": chat.ORACLE,
    "op9_quality_rules": quality.ORACLE,
}
