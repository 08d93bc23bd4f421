"""Quality gates on generated records: grounding, reward, diversity. Judges are column functions; the offline ones count overlap."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from refinery.config import REWARD_DIMENSIONS
from refinery.functions import scores, text as tx
from refinery.operators.dedup import vector_pairs
from refinery.operators.graph import first_independent_set
from refinery.operators.storage import materialize
from refinery.records import reject, undecided

SUPPORTED = 0.5
DENIAL = r"(?i)\b(not|never|no|n't)\b"


def answer_text() -> Column:
    """What the gates judge: the output; of a pair the chosen side; of a rollout group the response with the best score."""
    best = F.element_at("responses", F.coalesce(F.array_position("reward_scores", F.array_max("reward_scores")), F.lit(1)).cast("int"))
    kind = F.col("task_type")
    return F.when(kind == "preference", F.col("chosen")).when(kind == "grpo", best).otherwise(F.col("output"))


ASPECTS = ("accuracy", "grounding", "consistency", "own_words")


def claim_scores(answer: Column, source: Column, n: int = 3) -> Column:
    """array of struct(claim, accuracy, grounding, consistency, own_words, support) over the answer's sentences: its numbers are the source's; the share of
    its word n-grams that the source holds; it denies nothing where the source denies nothing; the share of its words that the source has (what is
    missing came from elsewhere). support is the least of the four."""
    numbers = lambda c: F.regexp_extract_all(c, F.lit(r"\d+"), F.lit(0))

    def one(claim: Column, e: Column) -> Column:
        words = F.array_distinct(tx.words(F.lower(claim)))
        known = F.size(F.array_intersect(words, e["words"])) / F.greatest(F.size(words), F.lit(1))
        many = tx.let(tx.word_ngrams(claim, n), lambda g: F.size(F.array_intersect(g, e["grams"])) / F.size(g))
        parts = F.struct(
            F.when(F.size(F.array_except(numbers(claim), e["numbers"])) > 0, 0.3).otherwise(1.0).alias("accuracy"), F.when(F.size(words) < n, known).otherwise(many).alias("grounding"),
            F.when(claim.rlike(DENIAL) & ~e["denies"], 0.3).otherwise(1.0).alias("consistency"), known.alias("own_words"),
        )
        return tx.let(parts, lambda p: F.struct(claim.alias("claim"), *[p[a].alias(a) for a in ASPECTS], F.least(*[p[a] for a in ASPECTS]).alias("support")))

    evidence = F.struct(tx.words(F.lower(source)).alias("words"), tx.word_ngrams(source, n).alias("grams"), source.rlike(DENIAL).alias("denies"), numbers(source).alias("numbers"))
    return tx.let(evidence, lambda e: F.transform(tx.sentences(answer), lambda c: one(c, e)))


def grounding_verdict(answer: Column, source: Column) -> Column:
    """struct(score, supported, unsupported, and the mean of each aspect); 0 without claims or source."""
    pick = lambda claims, good: F.transform(F.filter(claims, lambda c: (c["support"] >= SUPPORTED) == F.lit(good)), lambda c: c["claim"])
    mean = lambda claims, a: F.when(F.size(claims) > 0, F.aggregate(claims, F.lit(0.0), lambda t, c: t + c[a]) / F.size(claims)).otherwise(0.0)
    return tx.let(claim_scores(answer, F.coalesce(source, F.lit(""))), lambda claims: F.struct(_mean_support(claims).alias("score"), pick(claims, True).alias("supported"), pick(claims, False).alias("unsupported"), *[mean(claims, a).alias(a) for a in ASPECTS]))


def _mean_support(claims: Column) -> Column:
    return F.when(F.size(claims) > 0, F.aggregate(claims, F.lit(0.0), lambda a, c: a + c["support"]) / F.size(claims)).otherwise(0.0)


def grounding_score(answer: Column, source: Column, n: int = 3) -> Column:
    """The mean support of claim_scores, over Arrow. The JVM cuts the sentences and looks for denials."""
    source, claims = F.coalesce(source, F.lit("")), tx.sentences(answer)
    marks = F.array_join(F.transform(claims, lambda c: F.when(c.rlike(DENIAL), "1").otherwise("0")), "")
    return scores.mean_support(n)(F.lower(F.array_join(claims, "\n")), marks, F.lower(source), source.rlike(DENIAL))


def grounding_scores(answers: list[Column], source: Column, n: int = 3) -> Column:
    """grounding_score of each of several answers, as an array; what the source holds is taken once."""
    source, claims = F.coalesce(source, F.lit("")), [tx.sentences(a) for a in answers]
    marks = [F.array_join(F.transform(c, lambda x: F.when(x.rlike(DENIAL), "1").otherwise("0")), "") for c in claims]
    return scores.mean_supports(n)(F.array(*[F.lower(F.array_join(c, "\n")) for c in claims]), F.array(*marks), F.lower(source), source.rlike(DENIAL))


def lenient(score: Column, leniency: float = 0.15) -> Column:
    """A judge of the generator's own make: it forgives part of what is missing."""
    return F.least(F.lit(1.0), score + F.lit(leniency))


def grounding_gate(df: DataFrame, threshold: float = 0.7, judge: Callable[[Column, Column], Column] = grounding_score, evidence: str = "input") -> DataFrame:
    """Rejects answers that their evidence column doesn't bear out. The record's own input is exact evidence, without a join."""
    df = df.withColumn("grounding_score", judge(answer_text(), F.col(evidence)))
    return reject(df, F.col("grounding_score") < threshold, "grounding_below", "grounding_gate", F.format_string("%.2f", F.col("grounding_score")))


def retrieve_evidence(df: DataFrame, chunks: DataFrame, n: int = 3, common: int = 1000) -> DataFrame:
    """The baseline: adds retrieved, the chunk (of chunks: chunk) that shares most word n-grams with the answer. Of grams in more than `common` chunks an
    answer is told by its others; one that has no others is matched by its own, in `common` chunks drawn by hash at most, so no gram makes a square."""
    ask = df.select("id", F.explode(tx.word_ngrams(answer_text(), n)).alias("g"))
    have = materialize(chunks.select("chunk", F.xxhash64("chunk").alias("c")).dropDuplicates(["c"]), "chunks")
    grams = have.select("c", F.explode(tx.word_ngrams(F.col("chunk"), n)).alias("g"))
    held = materialize(grams.groupBy("g").agg(F.count(F.lit(1)).alias("held")), "held")
    few = held.where(F.col("held") <= common).select("g")
    hits = ask.join(grams.join(few, "g", "left_semi"), "g").groupBy("id", "c").agg(F.count(F.lit(1)).alias("n"))
    best = materialize(hits.groupBy("id").agg(F.max_by("c", F.struct("n", "c")).alias("c")), "best")
    many = held.where(F.col("held") > common).select("g", "held")
    drawn = grams.join(many, "g").where(F.pmod(F.xxhash64("c", "g"), F.ceil(F.col("held") / common).cast("long")) == 0).groupBy("g").agg(F.max("c").alias("c"))
    rest = ask.join(best.select("id"), "id", "left_anti").join(drawn, "g").groupBy("id").agg(F.max("c").alias("c"))
    best = best.unionByName(rest)
    return df.join(best.join(have, "c").select("id", F.col("chunk").alias("retrieved")), "id", "left")


def dimension_scores(instruction: Column, answer: Column) -> Column:
    """Map of the seven dimensions to scores in [0, 1], from the texts alone: length, how much of what the question names the answer takes up, repeats, and
    whether it begins and ends as sentences do (truthfulness stays neutral: its proxy would be the other gate's)."""
    bare = lambda t: F.transform(tx.words(F.lower(t)), lambda x: F.regexp_replace(x, r"[.,;:!?]", ""))
    named = F.array_distinct(F.filter(bare(instruction), lambda x: F.length(x) > 4))

    def scored(w: Column, ask: Column) -> Column:
        n = F.size(w)
        relevant = F.least(F.lit(1.0), F.when(F.size(ask) > 0, 2 * F.size(F.array_intersect(ask, w)) / F.size(ask)).otherwise(0.0))
        long = F.least(n / F.lit(12.0), F.lit(1.0))
        ends, starts = F.when(F.trim(answer).rlike(r"[.!?]$"), 1.0).otherwise(0.4), F.when(answer.rlike(r"^\p{Lu}"), 1.0).otherwise(0.4)
        values = {"helpfulness": F.least(long, relevant), "honesty": ends, "instruction_following": relevant, "truthfulness": F.lit(0.8), "depth": long, "creativity": F.when(n > 0, F.size(F.array_distinct(w)) / n).otherwise(0.0), "coherence": (ends + starts) / 2}
        return F.create_map(*[x for k in REWARD_DIMENSIONS for x in (F.lit(k), values[k].cast("double"))])

    return tx.let(bare(answer), lambda w: tx.let(named, lambda ask: scored(w, ask)))


def judge_notes(scores: Column) -> Column:
    """struct(strengths, weaknesses): the dimensions from 0.8 on, and those below 0.6 with their scores, in words."""
    named = lambda good: F.array_join(F.transform(F.filter(F.map_entries(scores), lambda e: (e["value"] >= 0.8) if good else (e["value"] < 0.6)), lambda e: F.concat(e["key"], F.lit(" "), F.format_string("%.2f", e["value"]))), ", ")
    return F.struct(named(True).alias("strengths"), named(False).alias("weaknesses"))


def reward_score(scores: Column, dimensions: tuple = REWARD_DIMENSIONS) -> Column:
    return tx.let(scores, lambda held: sum((F.element_at(held, F.lit(d)) for d in dimensions), F.lit(0.0)) / len(dimensions))


def weakest(scores: Column, dimensions: tuple = REWARD_DIMENSIONS) -> Column:
    """The dimension with the least score; ties in the order of the dimensions."""
    return F.array_min(F.array(*[F.struct(F.element_at(scores, F.lit(d)).alias("score"), F.lit(k).alias("k"), F.lit(d).alias("dimension")) for k, d in enumerate(dimensions)]))["dimension"]


def reward_gate(df: DataFrame, threshold: float = 0.7, dimensions: tuple = REWARD_DIMENSIONS, scorer: Callable[[Column, Column], Column] = dimension_scores) -> DataFrame:
    """Rejects answers whose mean over the dimensions is below the threshold. A pair needs chosen at or above it and rejected below it; a rejected side
    that is too good is a contrast failure, which no repair follows."""
    df = df.withColumn("reward_dimensions", scorer(F.col("instruction"), answer_text()))
    df = df.withColumn("reward_score", reward_score(F.col("reward_dimensions"), dimensions)).withColumn("weakest_dimension", weakest(F.col("reward_dimensions"), dimensions))
    df = reject(df, F.col("reward_score") < threshold, "reward_below", "reward_gate", F.format_string("%.2f", F.col("reward_score")))
    df = df.withColumn("judge_notes", judge_notes(F.col("reward_dimensions")))
    other = reward_score(scorer(F.col("instruction"), F.col("rejected")), dimensions)
    return reject(df, (F.col("task_type") == "preference") & (other >= threshold), "rejected_above_threshold", "reward_gate", F.format_string("%.2f", other))


def embed_text() -> Column:
    kind = F.col("task_type")
    return F.when(kind == "preference", F.col("chosen")).when(kind == "grpo", F.col("instruction")).when(kind == "language_modeling", F.col("output")).otherwise(F.concat_ws("\n", "instruction", "output"))


def hashed_encoder(dim: int = 256, n: int = 3):
    """The offline stand-in for a sentence encoder: hashed character n-grams, log counts, length one."""

    @F.pandas_udf("array<float>")
    def encode(texts: pd.Series) -> pd.Series:
        import zlib
        from collections import Counter

        place: dict[str, int] = {}  # of the n-grams met: texts of a batch share most of theirs

        def one(t):
            t = f" {(t or '').lower()} "
            grams = Counter(t[k : k + n] for k in range(len(t) - n + 1))
            for g in grams:
                if g not in place:
                    place[g] = zlib.crc32(g.encode("utf-8", "surrogatepass")) % dim
            v = np.bincount([place[g] for g in grams], weights=list(grams.values()), minlength=dim).astype(np.float64)
            v = np.log1p(v)
            return (v / max(np.linalg.norm(v), 1e-12)).astype(np.float32)

        return texts.map(one)

    return encode


#: Encoders by name; a user's own takes a column of texts to one of float arrays.
ENCODERS: dict[str, Callable] = {"hashed-3gram": hashed_encoder, "hashed-4gram": lambda: hashed_encoder(n=4)}


def register_encoder(name: str, make: Callable) -> None:
    ENCODERS[name] = make


#: Gates by name, beside the three: (records, configuration, context) to marked records.
CUSTOM_GATES: dict[str, Callable] = {}


def register_gate(name: str, gate: Callable) -> None:
    CUSTOM_GATES[name] = gate


def diversity_gate(df: DataFrame, threshold: float = 0.92, index: str = "auto", encoder=None) -> DataFrame:
    """Rejects a record whose cosine with an accepted earlier one (id order) exceeds the threshold: the same set as inserting one by one."""
    live = undecided(df)
    vectors = live.select("id", "embedding") if "embedding" in df.columns else live.select("id", (encoder or hashed_encoder())(embed_text()).alias("embedding"))
    dim = 64 if "embedding" in df.columns else 256
    pairs = vector_pairs(materialize(vectors.where("embedding is not null"), "vectors"), None, threshold, index, dim=dim)
    gone = first_independent_set(materialize(pairs.select("a", "b"), "pairs")).where("not kept").select(F.col("node").alias("id"), F.col("by").alias("_by"))
    return reject(df.join(materialize(gone, "gone"), "id", "left"), F.col("_by").isNotNull(), "not_diverse", "diversity_gate", F.col("_by")).drop("_by")
