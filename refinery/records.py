"""The canonical record, its identity, provenance and verdicts.

A step never drops a row: it marks it. The rows of a stage carry status, rejection_reason (`code:detail`) and rejecting_step;
accepted and rejected rows are two filters over one table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

TASK_TYPES = ("instruction_following", "conversational", "preference", "grpo", "language_modeling", "evol_instruct", "chain_of_thought", "unpaired_preference")
STEP_RECORD = T.StructType([T.StructField("step", T.StringType()), T.StructField("version", T.StringType()), T.StructField("ts", T.TimestampType()), T.StructField("config_hash", T.StringType()), T.StructField("notes", T.MapType(T.StringType(), T.StringType()))])
RECORD = T.StructType(
    [T.StructField(n, T.StringType()) for n in ("id", "source_uri", "instruction", "input", "output", "chosen", "rejected")]
    + [T.StructField("label", T.DoubleType()), T.StructField("responses", T.ArrayType(T.StringType())), T.StructField("reward_scores", T.ArrayType(T.DoubleType())), T.StructField("task_type", T.StringType()), T.StructField("metadata", T.MapType(T.StringType(), T.StringType())), T.StructField("provenance_chain", T.ArrayType(STEP_RECORD))]
)
VERDICT = ("status", "rejection_reason", "rejecting_step")
ACCEPTED, REJECTED = "accepted", "rejected"
#: Reason codes; a reason is `code` or `code:detail`.
REASONS = (
    "parse_failed preprocess_dropped schema_missing schema_too_short schema_too_long schema_encoding exact_duplicate near_duplicate embedding_duplicate seen_in_earlier_run secrets "
    "toxic_classifier toxic_judge generation_parse_failed grounding_below reward_below rejected_above_threshold not_diverse downsampled truncated source_cap late_record"
).split()


def stable_id(*parts: Column) -> Column:
    """A hash of the parts, laid out as a version-4 UUID: the same after a retry or a rerun."""
    h = F.sha2(F.concat_ws("\x1f", *[F.coalesce(p.cast("string"), F.lit("\x00")) for p in parts]), 256)
    variant = F.translate(F.substring(h, 17, 1), "0123456789abcdef", "89ab89ab89ab89ab")
    return F.concat(F.substring(h, 1, 8), F.lit("-"), F.substring(h, 9, 4), F.lit("-4"), F.substring(h, 14, 3), F.lit("-"), variant, F.substring(h, 18, 3), F.lit("-"), F.substring(h, 21, 12))


def to_records(df: DataFrame, mapping: dict[str, Column | str], task_type: str, source_uri: Column | str, identity: tuple = ()) -> DataFrame:
    """Canonical records of raw rows. mapping: canonical field to column (or name); all other fields are null.

    The id hashes the source, the identity columns and the mapped content. Metadata and the chain start empty."""
    col = lambda c: F.col(c) if isinstance(c, str) else c
    uri = F.lit(source_uri) if isinstance(source_uri, str) else source_uri
    kinds = {f.name: f.dataType for f in RECORD}
    fields = {n: (col(mapping[n]) if n in mapping else F.lit(None)).cast(t) for n, t in kinds.items() if n not in ("id", "source_uri", "task_type", "metadata", "provenance_chain")}
    content = [col(c) for c in identity] or [c.cast("string") for n, c in fields.items() if n in mapping]
    meta = mapping.get("metadata")
    return df.select(
        stable_id(uri, *content).alias("id"), uri.alias("source_uri"), *[c.alias(n) for n, c in fields.items()], F.lit(task_type).alias("task_type"),
        (col(meta) if meta is not None else F.create_map().cast(kinds["metadata"])).cast(kinds["metadata"]).alias("metadata"), F.array().cast(kinds["provenance_chain"]).alias("provenance_chain"),
        F.lit(ACCEPTED).alias("status"), F.lit(None).cast("string").alias("rejection_reason"), F.lit(None).cast("string").alias("rejecting_step"),
    ).select(*RECORD.fieldNames(), *VERDICT)


def append_provenance(df: DataFrame, step: str, config_hash: str = "", ts: str = "1970-01-01T00:00:00Z", notes: dict[str, Column] | None = None, version: str = "1", when: Column | None = None) -> DataFrame:
    """Add one step record at the end of the chain; earlier ones are never touched. The time is the run's, not the task's."""
    notes = F.create_map(*[x for k, v in (notes or {}).items() for x in (F.lit(k), v.cast("string"))]).cast(STEP_RECORD["notes"].dataType)
    entry = F.struct(F.lit(step).alias("step"), F.lit(version).alias("version"), F.lit(ts).cast("timestamp").alias("ts"), F.lit(config_hash).alias("config_hash"), notes.alias("notes"))
    chain = F.array_append("provenance_chain", entry)
    return df.withColumn("provenance_chain", chain if when is None else F.when(when, chain).otherwise(F.col("provenance_chain")))


def prefix_violations(before: DataFrame, after: DataFrame) -> DataFrame:
    """ids whose chain after a step doesn't begin with their chain before it."""
    a, b = before.select("id", F.col("provenance_chain").alias("was")), after.select("id", F.col("provenance_chain").alias("now"))
    key = lambda c: F.to_json(c)  # noqa: E731  maps aren't comparable
    return a.join(b, "id").where(key(F.slice("now", 1, F.greatest(F.size("was"), F.lit(0)))) != key(F.col("was"))).select("id")


def reject(df: DataFrame, when: Column, code: str, step: str, detail: Column | None = None) -> DataFrame:
    """Mark undecided rows that meet a condition; rows rejected earlier keep their first reason."""
    if code not in REASONS:
        raise ValueError(f"unknown reason code {code}")
    now = (F.col("status") == ACCEPTED) & F.coalesce(when, F.lit(False))
    reason = F.lit(code) if detail is None else F.concat(F.lit(f"{code}:"), F.coalesce(detail.cast("string"), F.lit("")))
    df = df.withColumn("_now", now)
    return df.withColumns({"rejection_reason": F.when(F.col("_now"), reason).otherwise(F.col("rejection_reason")), "rejecting_step": F.when(F.col("_now"), F.lit(step)).otherwise(F.col("rejecting_step")), "status": F.when(F.col("_now"), F.lit(REJECTED)).otherwise(F.col("status"))}).drop("_now")


def undecided(df: DataFrame) -> DataFrame:
    return df.where(F.col("status") == ACCEPTED)


def passed(df: DataFrame) -> DataFrame:
    return undecided(df).drop(*VERDICT)


def rejected(df: DataFrame) -> DataFrame:
    return df.where(F.col("status") == REJECTED)


def reason_code() -> Column:
    return F.regexp_extract("rejection_reason", "^[a-z_]+", 0)


def stage_counts(df: DataFrame, step: str) -> DataFrame:
    """step, n_in, n_accepted, n_rejected of a marked stage, one aggregation."""
    return df.agg(F.lit(step).alias("step"), F.count(F.lit(1)).alias("n_in"), F.count_if(F.col("status") == ACCEPTED).alias("n_accepted"), F.count_if((F.col("status") == REJECTED) & (F.col("rejecting_step") == step)).alias("n_rejected"))


def rejection_breakdown(df: DataFrame) -> DataFrame:
    """rejecting_step, code, n with totals (rollup; null is the total)."""
    return rejected(df).withColumn("code", reason_code()).rollup("rejecting_step", "code").agg(F.count(F.lit(1)).alias("n"))


def assert_conserved(n_in: int, n_accepted: int, n_rejected: int, n_generated: int = 0) -> None:
    """No silent drop: what came in (and what was generated) went out, accepted or rejected."""
    if n_in + n_generated != n_accepted + n_rejected:
        raise AssertionError(f"{n_in} rows in and {n_generated} generated, but {n_accepted} accepted and {n_rejected} rejected")
