"""The engine's functions by name in SQL, registered with a session."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: SQL functions (name, arguments, result, body); the optimizer inlines them.
FUNCTIONS = (
    ("refinery_tokens", "t string", "bigint", "size(filter(split(coalesce(t, ''), '\\\\s+'), w -> w <> ''))"),
    ("refinery_normal", "t string", "string", "trim(regexp_replace(lower(t), '\\\\s+', ' '))"),
    ("refinery_key", "t string", "string", "sha2(refinery_normal(t), 256)"),
    ("refinery_jaccard", "a array<string>, b array<string>", "double", "case when size(array_union(a, b)) = 0 then 1.0 else size(array_intersect(a, b)) / size(array_union(a, b)) end"),
)
#: Table functions: the first n words of a text, numbered.
TABLES = (("first_words", "t string, n int", "k int, word string", "select k, word from (select posexplode(slice(filter(split(coalesce(t, ''), '\\\\s+'), w -> w <> ''), 1, n)) as (k, word))"),)


def register(spark: SparkSession) -> None:
    """Makes the functions known to the session; again is harmless."""
    for name, takes, gives, body in FUNCTIONS:
        spark.sql(f"create or replace temporary function {name}({takes}) returns {gives} return {body}")
    for name, takes, gives, body in TABLES:
        spark.sql(f"create or replace temporary function {name}({takes}) returns table({gives}) return {body}")
