"""Frames and constants that the registered queries share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from refinery.records import to_records

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a function under its name, with its SQL if it has any."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def doc_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents as language-modelling records whose id is the doc_id."""
    docs = read(spark, sf_dir, "documents")
    made = to_records(docs, {"output": "text", "metadata": F.create_map(F.lit("lang"), F.coalesce("lang", F.lit("")), F.lit("source"), F.coalesce("source", F.lit("")), F.lit("doc_id"), F.col("doc_id").cast("string"))}, "language_modeling", F.coalesce(F.col("source"), F.lit("documents")), ("doc_id",))
    return made.withColumn("id", F.col("metadata")["doc_id"].cast("long"))
