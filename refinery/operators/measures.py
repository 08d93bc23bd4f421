"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from refinery.functions import scores


def overlap(df: DataFrame, one: Column, two: Column, by: tuple = ()) -> DataFrame:
    """Per group: rows, rejected by the first gate only, the second only, both, and the Jaccard of the two rejection sets; shares in percent."""
    both, first, second = F.count_if(one & two), F.count_if(one & ~two), F.count_if(~one & two)
    out = df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), first.alias("only1"), second.alias("only2"), both.alias("both"))
    union = F.col("only1") + F.col("only2") + F.col("both")
    return out.withColumn("jaccard", F.when(union > 0, F.col("both") / union).otherwise(0.0)).withColumns({f"{c}_pct": 100.0 * F.col(c) / F.col("n") for c in ("only1", "only2", "both")})


def injection_recall(verdicts: DataFrame, truth: DataFrame) -> DataFrame:
    """verdicts: qa_id, rejected, recovered. truth: qa_id, injected_type (null: clean). Per type and overall (null): injected, detected, recovered and both recalls."""
    rows = truth.where("injected_type is not null").join(verdicts, "qa_id", "left")
    out = rows.rollup("injected_type").agg(F.count(F.lit(1)).alias("injected"), F.count_if("rejected").alias("detected"), F.count_if(F.col("rejected") & F.col("recovered")).alias("recovered"))
    return out.withColumns({"detect_recall": F.col("detected") / F.col("injected"), "recover_recall": F.col("recovered") / F.col("injected")})


def confusion(verdicts: DataFrame, truth: DataFrame) -> DataFrame:
    """tp, fp, fn, tn, precision, recall, specificity of a gate against injected truth."""
    rows = truth.join(verdicts.select("qa_id", "rejected"), "qa_id")
    bad = F.col("injected_type").isNotNull()
    out = rows.agg(F.count_if(bad & F.col("rejected")).alias("tp"), F.count_if(~bad & F.col("rejected")).alias("fp"), F.count_if(bad & ~F.col("rejected")).alias("fn"), F.count_if(~bad & ~F.col("rejected")).alias("tn"))
    share = lambda a, b: F.when(F.col(a) + F.col(b) > 0, F.col(a) / (F.col(a) + F.col(b)))
    return out.withColumns({"precision": share("tp", "fp"), "recall": share("tp", "fn"), "specificity": share("tn", "fp")})


def yield_gain(hard: Column, adaptive: Column) -> Column:
    return F.when(hard > 0, adaptive / hard - 1)


def metric_deltas(df: DataFrame, by: str, condition: str, base: str, other: str, metrics: tuple) -> DataFrame:
    """One row a group and metric: its value under both conditions, and the absolute and relative change."""
    wide = df.groupBy(by).pivot(condition, [base, other]).agg(*[F.first(m).alias(m) for m in metrics])
    out = None
    for m in metrics:
        a, b = F.col(f"{base}_{m}"), F.col(f"{other}_{m}")
        row = wide.select(by, F.lit(m).alias("metric"), a.alias("base"), b.alias("other"), (b - a).alias("delta"), F.when(a != 0, (b - a) / a).alias("relative"))
        out = row if out is None else out.unionByName(row)
    return out


def match_f1(hyp: Column, ref: Column) -> Column:
    """The stand-in for an embedding-matched F1: each word takes its best match on the other side by the share of character bigrams in common."""
    return scores.match_f1(F.lower(F.coalesce(hyp, F.lit(""))), F.lower(F.coalesce(ref, F.lit(""))))


def call_usage(ledger: DataFrame) -> DataFrame:
    """model, calls, failed, tokens, latency percentiles, from the call ledger."""
    return ledger.groupBy("model").agg(F.count(F.lit(1)).alias("calls"), F.count_if(F.col("error").isNotNull()).alias("failed"), F.sum("prompt_tokens").alias("prompt_tokens"), F.sum("completion_tokens").alias("completion_tokens"), F.percentile_approx("latency", [0.5, 0.95]).alias("latency"))
