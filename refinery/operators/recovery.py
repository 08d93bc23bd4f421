"""Recovery: diagnose why an answer failed its grounding by probing the generator, repair it, or retry blindly (the baseline).

Probing runs in waves over undecided rows only. A row whose score is at or above the split starts with the temperature sweep, a lower one with the
strict prompt; no row costs more than five generations.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce
from operator import and_, or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from refinery.config import REWARD_DIMENSIONS
from refinery.functions import text as tx
from refinery.operators.gates import dimension_scores, grounding_score, reward_score
from refinery.operators.generation import EASE, Backend, Profile, call_id, run_calls, simulate
from refinery.operators.storage import materialize

#: Failure modes: where each arises, and whether a repair is tried.
FAILURE_MODES = (
    ("threshold_marginal", "gate", True), ("generator_temperature", "generator", True), ("generator_parametric", "generator", True), ("instruction_quality", "instruction", True), ("response_quality", "generator", True),
    ("domain_mismatch", "generator", True), ("source_ambiguous", "source", False), ("near_duplicate", "corpus", False), ("unknown", "unknown", False),
)

#: answers(rows, prompt kind, temperature, attempt) adds asked, answer and fault to rows.
Answers = Callable[[DataFrame, str, float, int], DataFrame]


def taxonomy(spark) -> DataFrame:
    return spark.createDataFrame(list(FAILURE_MODES), "mode string, origin string, recoverable boolean")


def simulated(profile: Profile, easing: dict = EASE) -> Answers:
    return lambda rows, prompt, temperature, attempt: simulate(rows, profile, prompt, temperature, attempt, easing=easing)


def extractive(key: str = "qa_id") -> Answers:
    """The offline generator of a run: the sentence of the passage that shares most words with the question; at the base prompt a hot call may give its words in
    disorder; a new question is put to a sentence drawn by hash."""

    def answers(rows: DataFrame, prompt: str, temperature: float, attempt: int) -> DataFrame:
        bare = lambda t: F.transform(tx.words(F.lower(t)), lambda x: F.regexp_replace(x, r"[.,;:!?]", ""))
        told = tx.let(bare(F.col("instruction")), lambda ask: F.array_max(F.transform(tx.sentences(F.col("input")), lambda s, k: F.struct(F.size(F.array_intersect(bare(s), ask)).alias("n"), (-k).alias("k"), s.alias("s")))))["s"]
        drawn = tx.let(tx.sentences(F.col("input")), lambda s: F.get(s, F.pmod(F.xxhash64(key), F.greatest(F.size(s), F.lit(1))).cast("int")))
        if prompt == "requestion":
            lead = F.regexp_replace(F.array_join(F.slice(tx.words(drawn), 1, 4), " "), r"[.,;:!?]", "")
            return rows.withColumns({"asked": F.concat(F.lit("What is said of "), lead, F.lit("?")), "answer": F.coalesce(drawn, F.lit("")), "fault": F.lit("none")})
        hot = (F.lit(prompt) == "base") & (tx.hash_unit(F.lit("hot"), F.col(key), F.lit(temperature), F.lit(attempt)) < temperature / 2)
        return rows.withColumns({"asked": F.col("instruction"), "answer": F.coalesce(F.when(hot, F.array_join(F.reverse(tx.words(told)), " ")).otherwise(told), F.lit("")), "fault": F.lit("none")})

    return answers


def networked(backend: Backend, ledger_dir: str, texts: dict, concurrency: int = 8, budget: int | None = None) -> Answers:
    """A backend behind the probe's prompts (templates answer, strict, domain, requestion); a new question is answered in a second call."""

    def ask(rows: DataFrame, name: str, temperature: float, attempt: int, question: Column) -> DataFrame:
        prompt = texts[name].render(source=F.col("input"), question=question)
        rows = rows.withColumn("_call", call_id(backend.model, prompt, F.lit(temperature), F.lit(attempt)))
        said = run_calls(rows.select(F.col("_call").alias("call_id"), prompt.alias("prompt"), F.lit(temperature).alias("temperature")), backend, ledger_dir, concurrency, budget=budget)
        return rows.join(said.select(F.col("call_id").alias("_call"), F.col("text").alias("_said")), "_call", "left").drop("_call")

    def answers(rows: DataFrame, prompt: str, temperature: float, attempt: int) -> DataFrame:
        asked = F.col("instruction")
        if prompt == "requestion":
            rows = ask(rows, "requestion", temperature, attempt, asked).withColumn("_asked", F.coalesce("_said", asked)).drop("_said")
            return ask(rows, "answer", temperature, attempt, F.col("_asked")).withColumnsRenamed({"_said": "answer", "_asked": "asked"}).withColumn("fault", F.lit("none"))
        rows = ask(rows, {"base": "answer"}.get(prompt, prompt), temperature, attempt, asked)
        return rows.withColumnRenamed("_said", "answer").withColumns({"asked": asked, "fault": F.lit("none")})

    return answers


class FrameJudge:
    """A judge that needs the whole frame (one behind a backend): it adds judge_score to rows with answer and input."""

    def __init__(self, score: Callable[[DataFrame], DataFrame]):
        self.score = score


def _try(rows: DataFrame, answers: Answers, prompt: str, temperature: float, attempt: int, threshold: float, judge, also=None) -> DataFrame:
    """One attempt: the row's other columns, with try_answer, try_asked, try_score and try_pass. `also` (question, answer) is the next gate's verdict, where
    a repair has to meet it too."""
    rows = answers(rows.drop("asked", "answer", "fault"), prompt, temperature, attempt)
    if isinstance(judge, FrameJudge):
        rows = judge.score(rows).withColumnRenamed("judge_score", "_score")
        score = F.coalesce("_score", F.lit(0.0))
    else:
        score = F.coalesce(judge(F.col("answer"), F.col("input")), F.lit(0.0))
    rows = rows.withColumns({"try_asked": F.col("asked"), "try_answer": F.col("answer"), "try_score": score})
    passes = F.col("try_score") >= threshold
    return rows.withColumn("try_pass", passes & also(F.col("asked"), F.col("answer")) if also else passes).drop("asked", "answer", "fault", "_score")


def _try_all(rows: DataFrame, answers: Answers, tries: list[tuple[str, float, int]], threshold: float, judge, also=None) -> DataFrame:
    """All attempts side by side: adds asked_k, answer_k and try_pass_k for each (prompt, temperature, attempt). The judge meets each source once."""
    rows = rows.drop("asked", "answer", "fault")
    for k, (prompt, temperature, attempt) in enumerate(tries):
        rows = answers(rows, prompt, temperature, attempt).withColumnsRenamed({"asked": f"asked_{k}", "answer": f"answer_{k}"}).drop("fault")
    every = range(len(tries))
    rows = rows.withColumns({f"_score_{k}": F.coalesce(judge(F.col(f"answer_{k}"), F.col("input")), F.lit(0.0)) for k in every})
    passes = lambda k: (F.col(f"_score_{k}") >= threshold) & (also(F.col(f"asked_{k}"), F.col(f"answer_{k}")) if also else F.lit(True))
    return rows.withColumns({f"try_pass_{k}": F.coalesce(passes(k), F.lit(False)) for k in every})


def diagnose(failed: DataFrame, answers: Answers, threshold: float = 0.7, temperatures: tuple = (0.3, 0.5), split: float = 0.5, base_temperature: float = 0.7, judge=grounding_score, max_calls: int = 5, also=None, one_pass: bool = False) -> DataFrame:
    """failed: qa_id, grounding_score and what `answers` needs. Returns qa_id, mode, recovered, calls, final_answer, final_asked for each row.

    Ascending temperatures: all pass, the threshold was marginal; only a lower part of them passes, the temperature was at fault; else the sweep
    settles nothing. Then (or before, for low scores) the strict prompt, the domain prompt, a new question. If all fail: the source is
    ambiguous, or unknown where some part of the sweep passed. With one_pass, where answers and judge are column functions that cost no call, all attempts
    are computed in one pass and the waves are read off them: the same rows, calls counted as the waves make them, no table a wave."""
    temps = tuple(sorted(temperatures))
    cost = len(temps)
    if cost + 3 > max_calls:
        raise ValueError(f"{cost} temperatures and three prompts are more than {max_calls} calls")
    keep = ["qa_id", "mode", "calls", "final_answer", "final_asked"]
    if one_pass:
        tries = [("base", t, 1 + k) for k, t in enumerate(temps)] + [(p, temps[0], 1) for p in ("strict", "domain", "requestion")]
        rows, ok = _try_all(failed.where("grounding_score is not null"), answers, tries, threshold, judge, also), [F.col(f"try_pass_{k}") for k in range(cost)]
        prefix = [reduce(and_, [x if k < cut else ~x for k, x in enumerate(ok)]) for cut in range(1, cost)]
        mixed, high = reduce(or_, ok), F.col("grounding_score") >= split
        swept = F.when(reduce(and_, ok), "threshold_marginal").when(reduce(or_, prefix, F.lit(False)), "generator_temperature")
        end = lambda mode, calls, k: F.struct(mode.alias("mode"), F.lit(calls).alias("calls"), *[(F.lit(None).cast("string") if k is None else F.col(f"{c}_{k}")).alias(f"final_{c}") for c in ("answer", "asked")])
        strict = lambda calls: (F.col(f"try_pass_{cost}"), end(F.lit("generator_parametric"), calls, cost))
        sweep_ = lambda calls: (F.col("_swept").isNotNull(), end(F.col("_swept"), calls, 0))
        late = [(F.col(f"try_pass_{cost + j}"), end(F.lit(mode), cost + 1 + j, cost + j)) for j, mode in ((1, "domain_mismatch"), (2, "instruction_quality"))]
        last = end(F.when(mixed, "unknown").otherwise("source_ambiguous"), cost + 3, None)
        route = lambda ends: reduce(lambda rest, e: F.when(e[0], e[1]).otherwise(rest), reversed(ends), last)
        rows = rows.withColumn("_swept", swept).select("qa_id", F.when(high, route([sweep_(cost), strict(cost + 1), *late])).otherwise(route([strict(1), sweep_(cost + 1), *late])).alias("e"))
        return rows.select("qa_id", "e.mode", "e.calls", "e.final_answer", "e.final_asked").withColumn("recovered", F.col("final_answer").isNotNull())
    base = failed.withColumns({"calls": F.lit(0), "mixed": F.lit(False)})
    fresh = base.columns

    def settle(rows: DataFrame, mode: Column | str, answer: Column | str, asked: Column | str) -> DataFrame:
        return rows.select("qa_id", (F.lit(mode) if isinstance(mode, str) else mode).alias("mode"), "calls", F.col(answer).alias("final_answer") if isinstance(answer, str) else answer.alias("final_answer"), F.col(asked).alias("final_asked") if isinstance(asked, str) else asked.alias("final_asked"))

    def sweep(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
        for k, t in enumerate(temps):
            rows = _try(rows, answers, "base", t, 1 + k, threshold, judge, also)
            rows = rows.withColumnsRenamed({c: f"{c}_{k}" for c in ("try_asked", "try_answer", "try_score", "try_pass")})
        rows = rows.withColumn("calls", F.col("calls") + cost)
        ok = [F.col(f"try_pass_{k}") for k in range(len(temps))]
        all_pass, prefix = ok[0], F.lit(False)
        for x in ok[1:]:
            all_pass = all_pass & x
        for cut in range(1, len(ok)):
            part = F.lit(True)
            for k, x in enumerate(ok):
                part = part & (x if k < cut else ~x)
            prefix = prefix | part
        any_pass = ok[0]
        for x in ok[1:]:
            any_pass = any_pass | x
        rows = materialize(rows.withColumns({"mode": F.when(all_pass, "threshold_marginal").when(prefix, "generator_temperature"), "mixed": any_pass}), "sweep")
        return settle(rows.where("mode is not null"), F.col("mode"), "try_answer_0", "try_asked_0"), rows.where("mode is null").select(*fresh)

    def variant(rows: DataFrame, prompt: str, mode: str) -> tuple[DataFrame, DataFrame]:
        rows = _try(rows, answers, prompt, temps[0], 1, threshold, judge, also).withColumn("calls", F.col("calls") + 1)
        rows = materialize(rows, prompt)
        return settle(rows.where("try_pass"), mode, "try_answer", "try_asked"), rows.where("not try_pass").select(*fresh)

    high, low = base.where(F.col("grounding_score") >= split), base.where(F.col("grounding_score") < split)
    settled = []
    for first, rows in (("sweep", high), ("strict", low)):
        rows = materialize(rows, "probe")
        if first == "sweep":
            done, rows = sweep(rows)
            settled.append(done)
            done, rows = variant(rows, "strict", "generator_parametric")
        else:
            done, rows = variant(rows, "strict", "generator_parametric")
            settled.append(done)
            done, rows = sweep(rows)
        settled.append(done)
        for prompt, mode in (("domain", "domain_mismatch"), ("requestion", "instruction_quality")):
            done, rows = variant(rows, prompt, mode)
            settled.append(done)
        settled.append(settle(rows, F.when(F.col("mixed"), "unknown").otherwise("source_ambiguous"), F.lit(None).cast("string"), F.lit(None).cast("string")))
    out = settled[0]
    for x in settled[1:]:
        out = out.unionByName(x)
    return out.select(*keep).withColumn("recovered", F.col("final_answer").isNotNull())


def retry(failed: DataFrame, answers: Answers, threshold: float = 0.7, max_retries: int = 5, temperature: float = 0.7, judge=grounding_score, also=None, one_pass: bool = False) -> DataFrame:
    """The baseline: the same prompt and temperature again until one passes. Same columns as diagnose; mode null."""
    if one_pass:
        rows = _try_all(failed, answers, [("base", temperature, 1 + k) for k in range(max_retries)], threshold, judge, also)
        pick = lambda values, rest: reduce(lambda other, k: F.when(F.col(f"try_pass_{k}"), values(k)).otherwise(other), reversed(range(max_retries)), rest)
        none = F.lit(None).cast("string")
        rows = rows.select("qa_id", none.alias("mode"), pick(lambda k: F.lit(k + 1), F.lit(max_retries)).alias("calls"), *[pick(lambda k, c=c: F.col(f"{c}_{k}"), none).alias(f"final_{c}") for c in ("answer", "asked")])
        return rows.withColumn("recovered", F.col("final_answer").isNotNull())
    left = failed.withColumn("calls", F.lit(0))
    fresh, settled = left.columns, []
    for k in range(max_retries):
        rows = materialize(_try(left, answers, "base", temperature, 1 + k, threshold, judge, also).withColumn("calls", F.col("calls") + 1), "retry")
        settled.append(rows.where("try_pass").select("qa_id", F.lit(None).cast("string").alias("mode"), "calls", F.col("try_answer").alias("final_answer"), F.col("try_asked").alias("final_asked")))
        left = rows.where("not try_pass").select(*fresh)
    settled.append(left.select("qa_id", F.lit(None).cast("string").alias("mode"), "calls", F.lit(None).cast("string").alias("final_answer"), F.lit(None).cast("string").alias("final_asked")))
    out = settled[0]
    for x in settled[1:]:
        out = out.unionByName(x)
    return out.withColumn("recovered", F.col("final_answer").isNotNull())


#: One rewrite for the weakest dimension, as a function of (instruction, answer, source); it takes its words from these three.
_NAMED = lambda i: F.array_join(F.filter(tx.words(F.regexp_replace(i, r"[.,;:!?]", "")), lambda x: F.length(x) > 4), " ")
_CLOSED = lambda a: F.concat(F.upper(F.substring(a, 1, 1)), F.substr(a, F.lit(2)), F.when(F.trim(a).rlike(r"[.!?]$"), F.lit("")).otherwise(F.lit(".")))
_LONGER = lambda i, a, s: F.concat_ws(" ", _CLOSED(a), F.get(tx.sentences(s), F.lit(0)))
REWRITES: dict[str, Callable[[Column, Column, Column], Column]] = {
    "depth": _LONGER, "helpfulness": _LONGER, "coherence": lambda i, a, s: _CLOSED(a), "honesty": lambda i, a, s: _CLOSED(a), "instruction_following": lambda i, a, s: F.concat(_CLOSED(_NAMED(i)), F.lit(" "), _CLOSED(a)),
}


def refine(failed: DataFrame, threshold: float = 0.7, scorer=dimension_scores, dimensions: tuple = REWARD_DIMENSIONS, rewrite=None) -> DataFrame:
    """failed: instruction, output (or chosen), input, weakest_dimension, judge_notes, rejection_reason. One rewrite aimed at the weakest dimension, judged by the
    same gate. Adds refined, refined_score, repaired. Contrast failures are left out. For pairs the rewrite is the new chosen side. `rewrite` (rows to rows
    with refined) is a backend's; the offline one is REWRITES."""
    rows = failed.where(~F.coalesce(F.col("rejection_reason").startswith("rejected_above_threshold"), F.lit(False)))
    answer = F.when(F.col("task_type") == "preference", F.col("chosen")).otherwise(F.col("output"))
    if rewrite is not None:
        rows = rewrite(rows.withColumn("_answer", answer)).drop("_answer")
    else:
        new = answer
        for dimension, write in REWRITES.items():
            new = F.when(F.col("weakest_dimension") == dimension, write(F.col("instruction"), answer, F.coalesce("input", F.lit("")))).otherwise(new)
        rows = rows.withColumn("refined", new)
    rows = rows.withColumn("refined_score", reward_score(scorer(F.col("instruction"), F.col("refined")), dimensions))
    return rows.withColumn("repaired", F.coalesce(F.col("refined_score") >= threshold, F.lit(False)))


def networked_rewrite(backend: Backend, ledger_dir: str, template, temperature: float, concurrency: int = 8, budget: int | None = None):
    """A backend's rewrite: the weakest dimension, the judge's note and the passage go into the template."""

    def rewrite(rows: DataFrame) -> DataFrame:
        prompt = template.render(dimension=F.col("weakest_dimension"), note=F.col("judge_notes.weaknesses"), source=F.col("input"), answer=F.col("_answer"))
        rows = rows.withColumn("_call", call_id(backend.model, prompt, F.lit(temperature), F.lit(0)))
        said = run_calls(rows.select(F.col("_call").alias("call_id"), prompt.alias("prompt"), F.lit(temperature).alias("temperature")), backend, ledger_dir, concurrency, budget=budget)
        return rows.join(said.select(F.col("call_id").alias("_call"), F.col("text").alias("refined")), "_call", "left").drop("_call")

    return rewrite


def diagnostics(diagnosed: DataFrame) -> DataFrame:
    """mode, n, recovered, calls, with a total row (null mode)."""
    return diagnosed.rollup("mode").agg(F.count(F.lit(1)).alias("n"), F.count_if("recovered").alias("recovered"), F.sum("calls").alias("calls"))
