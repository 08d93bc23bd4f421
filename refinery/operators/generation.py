"""Generation tasks over pluggable backends, with a call ledger; offline backends are deterministic stand-ins.

A backend turns a frame of calls (call_id, prompt_kind, source, question, temperature, attempt) into text, on the JVM: the offline ones
are column expressions, so no call is paid twice by a recomputed plan. Networked backends go through `run_calls` with a ledger table.
"""

from __future__ import annotations

import string
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from refinery.functions import text as tx
from refinery.operators.storage import materialize

INJECTIONS = ("contradicts_source", "parametric_drift", "domain_mismatch", "instruction_quality", "high_temperature_drift")


class PromptTemplate:
    """A template whose placeholders are checked when it is made."""

    def __init__(self, text: str, required: tuple[str, ...]):
        self.text, self.required = text, required
        found = {name for _, name, _, _ in string.Formatter().parse(text) if name}
        if lacking := sorted(set(required) - found):
            raise ValueError(f"template lacks {lacking}; it must name all of {sorted(required)}")

    def render(self, **values: Column) -> Column:
        parts = []
        for literal, name, _, _ in string.Formatter().parse(self.text):
            parts.append(F.lit(literal))
            if name:
                parts.append(F.coalesce(values[name], F.lit("")))
        return F.concat(*parts)


TEMPLATES = {
    "qa": PromptTemplate("Write {n} questions of {difficulty} difficulty with answers from this passage, as a JSON array of objects with question and answer.\n{source}", ("n", "difficulty", "source")),
    "qa_table": PromptTemplate("Write {n} questions of {difficulty} difficulty that the rows of this table answer, as a JSON array of objects with question and answer.\n{source}", ("n", "difficulty", "source")),
    "preference": PromptTemplate("Write a question on the passage, a good answer and a poor one, as JSON with question, chosen, rejected.\n{source}", ("source",)),
    "grpo": PromptTemplate("Answer from the passage.\nPassage: {source}\nQuestion: {question}", ("source", "question")),
    "multiturn": PromptTemplate("Write a dialogue of {n} turns each about the passage, as a JSON array of objects with role and content.\n{source}", ("n", "source")),
    "evol": PromptTemplate("Rewrite the instruction ({strategy}); keep to the passage.\nPassage: {source}\nInstruction: {question}", ("strategy", "source", "question")),
    "cot": PromptTemplate("Reason step by step from the passage to the answer.\nPassage: {source}\nQuestion: {question}", ("source", "question")),
    "answer": PromptTemplate("Answer from the passage.\nPassage: {source}\nQuestion: {question}", ("source", "question")),
    "strict": PromptTemplate("Use only statements that the passage makes.\nPassage: {source}\nQuestion: {question}", ("source", "question")),
    "domain": PromptTemplate("Keep to the passage's subject and terms.\nPassage: {source}\nQuestion: {question}", ("source", "question")),
    "requestion": PromptTemplate("Write a question that this passage answers:\n{source}\nIt replaces: {question}", ("source", "question")),
    "refine": PromptTemplate("Rewrite the answer. Weakest: {dimension}. Note: {note}\nPassage: {source}\nAnswer: {answer}", ("dimension", "note", "source", "answer")),
    "ground": PromptTemplate("Judge the answer by the passage: JSON with score (0 to 1), supported and unsupported.\nPassage: {source}\nAnswer: {answer}", ("source", "answer")),
    "reward": PromptTemplate("Score the answer in {dimensions}: JSON with scores, overall, strengths and weaknesses.\nQuestion: {question}\nAnswer: {answer}", ("dimensions", "question", "answer")),
}


def templates(overrides: dict[str, str] | None = None) -> dict[str, PromptTemplate]:
    """The templates with a user's own in place; an unknown name, or a text without a placeholder that its template needs, raises."""
    if odd := sorted(set(overrides or {}) - set(TEMPLATES)):
        raise ValueError(f"no templates {odd}; there are {sorted(TEMPLATES)}")
    return TEMPLATES | {name: PromptTemplate(text, TEMPLATES[name].required) for name, text in (overrides or {}).items()}


# ---- chunks -------------------------------------------------------------------------------------------------------------------


def chunk_fixed(df: DataFrame, max_tokens: int = 512, overlap: int = 50) -> DataFrame:
    """df: id, text. id, chunk_no, chunk, n_tokens: runs of at most max_tokens words that step by max_tokens - overlap."""
    if not 0 <= overlap < max_tokens:
        raise ValueError("overlap must be below max_tokens")
    step = max_tokens - overlap
    w = df.select("id", tx.words(F.col("text")).alias("w")).where(F.size("w") > 0)
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.size("w") - overlap - 1), F.lit(step))
    rows = w.select("id", "w", F.posexplode(starts).alias("chunk_no", "at"))
    return rows.select("id", "chunk_no", F.array_join(F.slice("w", F.col("at") + 1, F.lit(max_tokens)), " ").alias("chunk"), F.size(F.slice("w", F.col("at") + 1, F.lit(max_tokens))).cast("long").alias("n_tokens"))


def chunk_paragraph(df: DataFrame) -> DataFrame:
    """One chunk a non-empty line."""
    rows = df.select("id", F.filter(F.split("text", "\n"), lambda p: F.trim(p) != "").alias("p")).select("id", F.posexplode("p").alias("chunk_no", "chunk"))
    return rows.select("id", "chunk_no", F.trim("chunk").alias("chunk"), tx.token_count(F.col("chunk")).alias("n_tokens"))


def chunk_headings(df: DataFrame) -> DataFrame:
    """df: id, html. One chunk a heading and what follows it: id, chunk_no, heading, chunk, n_tokens, is_table."""
    body = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style|nav|head|footer)\b.*?</\1\s*>", " "), r"(?s)<!--.*?-->", " ")
    parts = F.filter(F.split(body, r"(?i)(?=<h[1-6][ >])"), lambda p: p.rlike(r"(?i)^<h[1-6][ >]"))
    rows = df.select("id", F.posexplode(parts).alias("chunk_no", "part"))
    plain = lambda c: tx.collapse_space(tx.strip_html(c), False)
    rows = rows.select("id", "chunk_no", plain(F.regexp_extract("part", r"(?is)^<h([1-6])[^>]*>(.*?)</h\1>", 2)).alias("heading"), plain(F.col("part")).alias("chunk"), F.col("part").rlike("(?i)<table").alias("is_table"))
    return rows.withColumn("n_tokens", tx.token_count(F.col("chunk")))


def chunk_sections(df: DataFrame) -> DataFrame:
    """df: id, text. One chunk a heading line (# marks before it) and what follows it; what stands before the first heading is one too."""
    parts = F.filter(F.split("text", r"\n(?=#{1,6} )"), lambda p: F.trim(p) != "")
    rows = df.select("id", F.posexplode(parts).alias("chunk_no", "chunk"))
    return rows.select("id", "chunk_no", F.regexp_extract("chunk", r"^#{1,6} +([^\n]*)", 1).alias("heading"), F.trim("chunk").alias("chunk"), tx.token_count(F.col("chunk")).alias("n_tokens"), F.col("chunk").rlike(r"(?m)^\|.*\|").alias("is_table"))


def capped(chunks: DataFrame, max_tokens: int, overlap: int) -> DataFrame:
    """Chunks over the cap are cut again, with the overlap; the others, and tables, stay. Numbers follow the order."""
    long = (F.col("n_tokens") > max_tokens) & ~F.col("is_table")
    pieces = chunk_fixed(chunks.where(long).select(F.struct("id", "chunk_no", "heading").alias("id"), F.col("chunk").alias("text")), max_tokens, overlap)
    cut = pieces.select("id.id", F.col("id.chunk_no").alias("major"), F.col("chunk_no").alias("minor"), "id.heading", "chunk", "n_tokens", F.lit(False).alias("is_table"))
    whole = chunks.where(~long).select("id", F.col("chunk_no").alias("major"), F.lit(0).alias("minor"), "heading", "chunk", "n_tokens", "is_table")
    both = cut.unionByName(whole)
    return both.withColumn("chunk_no", F.row_number().over(Window.partitionBy("id").orderBy("major", "minor")) - 1).select("id", "chunk_no", "heading", "chunk", "n_tokens", "is_table")


def chunk(df: DataFrame, strategy: str = "heading", max_tokens: int = 512, overlap: int = 50, tables: bool = False) -> DataFrame:
    """df: id, text (or html). id, chunk_no, heading, chunk, n_tokens, is_table by a strategy; all but paragraphs keep to the cap. With
    `tables`, each table is a chunk of its own as well."""
    html = "html" in df.columns
    if strategy == "heading":
        rows = capped(chunk_headings(df) if html else chunk_sections(df), max_tokens, overlap)
    else:
        texts = df.select("id", tx.collapse_space(tx.strip_html(F.col("html"))).alias("text")) if html else df
        rows = chunk_fixed(texts, max_tokens, overlap) if strategy == "fixed" else chunk_paragraph(texts)
        rows = rows.select("id", "chunk_no", F.lit(None).cast("string").alias("heading"), "chunk", "n_tokens", F.lit(False).alias("is_table"))
    if tables:
        found = extract_tables(df).select("id", (F.col("table_no") + 1_000_000).alias("chunk_no"), F.lit(None).cast("string").alias("heading"), F.col("table").alias("chunk"), tx.token_count(F.col("table")).alias("n_tokens"), F.lit(True).alias("is_table"))
        rows = rows.unionByName(found)
    return rows


def extract_tables(df: DataFrame) -> DataFrame:
    """id, table_no, table: html tables, or runs of lines with two cells or more between pipes (df: id, text or html)."""
    source = "html" if "html" in df.columns else "text"
    if source == "html":
        found = F.regexp_extract_all("html", F.lit(r"(?is)<table\b.*?</table\s*>"), F.lit(0))
    else:
        # lines of fewer than three cells become a mark, and the text is cut at the marks
        marked = F.transform(F.split("text", "\n"), lambda x: F.when(F.size(F.split(x, "[|]")) >= 3, x).otherwise(F.lit("\x01")))
        found = F.transform(F.split(F.array_join(marked, "\n"), "\x01"), lambda x: F.regexp_replace(x, r"^\n+|\n+$", ""))
    return df.select("id", F.posexplode(F.filter(found, lambda t: t != "")).alias("table_no", "table"))


# ---- offline generation -------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Profile:
    """A simulated generator: chances of a drifted answer at temperature 0, its rise with temperature, of an answer from outside the source, of one
    from another subject, and of a faulty question. Fixed before any measurement, and blind to injected truth."""

    drift: float
    slope: float
    parametric: float
    domain: float
    question: float


PROFILES = {"small": Profile(0.06, 0.22, 0.16, 0.08, 0.14), "medium": Profile(0.04, 0.16, 0.12, 0.06, 0.11), "large": Profile(0.03, 0.12, 0.09, 0.05, 0.09)}
#: How far each prompt eases the lasting faults and the drift of the simulated generator: (drift, parametric, domain, question). That the strict prompt
#: eases knowledge from outside, and so on, is put in by hand; NEUTRAL is the control, in which no prompt eases anything.
EASE = {"base": (1.0, 1.0, 1.0, 1.0), "strict": (0.5, 0.2, 1.0, 1.0), "domain": (0.7, 0.6, 0.2, 1.0), "requestion": (0.7, 0.6, 0.6, 0.2)}
NEUTRAL = dict.fromkeys(EASE, (1.0, 1.0, 1.0, 1.0))


def eased(share: float) -> dict[str, tuple]:
    """EASE in part: 0 is NEUTRAL, 1 is EASE."""
    return {p: tuple(1 + share * (f - 1) for f in factors) for p, factors in EASE.items()}


def qa_pairs(chunks: DataFrame, n: int = 3, difficulty: str = "medium", multi_passage: bool = False) -> DataFrame:
    """Extractive QA: chunks (id, chunk_no, chunk) to qa_id, id, chunk_no, k, instruction, output, input. The answers are sentences of the chunk (one,
    two or three by difficulty), spread over it by k; the question asks for what the sentence says after its first words."""
    if multi_passage:
        chunks = chunks.withColumn("chunk", F.concat_ws("\n", "chunk", F.lead("chunk").over(Window.partitionBy("id").orderBy("chunk_no"))))
    take = {"easy": 1, "medium": 1, "hard": 2}[difficulty]
    s = chunks.withColumn("s", F.filter(tx.sentences(F.col("chunk")), lambda x: tx.token_count(x) >= 5)).where(F.size("s") > 0)
    rows = s.withColumn("k", F.explode(F.sequence(F.lit(0), F.least(F.lit(n), F.size("s")) - 1)))
    at = F.floor(F.col("k") * F.size("s") / F.least(F.lit(n), F.size("s"))).cast("int")
    answer = F.array_join(F.slice("s", at + 1, F.lit(take)), " ")
    lead = F.array_join(F.slice(tx.words(F.element_at("s", at + 1)), 1, 4), " ")
    about = F.regexp_replace(lead, r"[.,;:!?]", "")
    question = F.concat(F.lit("What does the passage say about "), about, F.lit("?"))
    if "is_table" in chunks.columns:
        question = F.when(F.col("is_table"), F.concat(F.lit("Which row of the table holds "), about, F.lit("?"))).otherwise(question)
    return rows.select(F.md5(F.concat_ws("|", F.col("id").cast("string"), F.col("chunk_no").cast("string"), F.col("k").cast("string"))).alias("qa_id"), "id", "chunk_no", "k", question.alias("instruction"), answer.alias("output"), F.col("chunk").alias("input"))


#: Answers of other documents that damages draw from; a bounded table (MOST rows of at most LONG characters), so it may be broadcast.
MOST, LONG = 1024, 2_000


def other_source(qa: DataFrame) -> DataFrame:
    """Adds alien and alien_ask: the answer and question of a pair of another part of the table, from MOST pairs drawn by hash."""
    drawn = qa.where(F.length("output") <= LONG).groupBy(tx.hash_int(MOST, F.lit("alien"), F.col("qa_id")).alias("_g")).agg(F.min(F.struct(F.md5(F.concat(F.lit("draw"), "qa_id")).alias("h"), F.col("qa_id").alias("_from"), F.col("output").alias("alien"), F.col("instruction").alias("alien_ask"))).alias("r"))
    order = Window.orderBy("_g")  # MOST rows
    drawn = drawn.select((F.row_number().over(order) - 1).alias("_k"), "r.*", F.coalesce(F.lead("r").over(order), F.first("r").over(Window.orderBy("_g").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))).alias("_next"))
    drawn = materialize(drawn, "aliens")
    n = max(1, drawn.count())
    rows = qa.withColumn("_k", tx.hash_int(n, F.lit("pick"), F.col("qa_id"))).join(F.broadcast(drawn.drop("h")), "_k", "left")
    own = F.col("_from") == F.col("qa_id")
    return rows.withColumns({"alien": F.coalesce(F.when(own, F.col("_next.alien")).otherwise(F.col("alien")), F.lit("")), "alien_ask": F.coalesce(F.when(own, F.col("_next.alien_ask")).otherwise(F.col("alien_ask")), F.lit(""))}).drop("_k", "_from", "_next")


def damaged(kind: Column, qa: dict[str, Column]) -> tuple[Column, Column]:
    """(instruction, output) of a pair after a damage of a kind. All that is put in comes from the tables (numbers moved on, words, answers and
    questions of other documents, order turned round), so there is no phrase that a judge could look for."""
    out, ask, alien = qa["output"], qa["instruction"], qa["alien"]
    w, x = tx.words(out), tx.words(alien)
    part = lambda share: F.floor(F.size(w) * share).cast("int")
    swapped = F.concat(F.slice(w, 1, part(0.3)), F.slice(x, 1, F.greatest(F.size(w) - 2 * part(0.3), F.lit(1))), F.slice(w, F.size(w) - part(0.3) + 1, part(0.3)))
    new = (
        F.when(kind == "contradicts_source", F.translate(F.array_join(swapped, " "), "0123456789", "1234567890"))
        .when(kind == "parametric_drift", F.array_join(F.concat(F.slice(w, 1, F.greatest(part(0.4), F.lit(1))), x), " "))
        .when(kind == "domain_mismatch", alien)
        .when(kind == "high_temperature_drift", F.array_join(F.reverse(w), " "))
        .otherwise(out)  # a faulty question keeps its answer
    )
    return F.when(kind == "instruction_quality", qa["alien_ask"]).otherwise(ask), new


def inject(qa: DataFrame, rate: float = 0.2, types: tuple = INJECTIONS[:4], seed: str = "inject") -> tuple[DataFrame, DataFrame]:
    """Damages a hash-chosen share of the pairs. Returns the pairs, without any trace of it, and the truth (qa_id, injected_type)."""
    rows = other_source(qa)
    kind = F.when(tx.hash_unit(F.lit(seed), F.col("qa_id")) < rate, F.element_at(F.array(*map(F.lit, types)), tx.hash_int(len(types), F.lit(seed + "-type"), F.col("qa_id")) + 1))
    ask, out = damaged(F.col("_kind"), {c: F.col(c) for c in ("instruction", "output", "alien", "alien_ask")})
    return rows.withColumn("_kind", kind).withColumns({"instruction": ask, "output": out}).drop("alien", "alien_ask", "_kind"), qa.select("qa_id", kind.alias("injected_type"))


def simulate(qa: DataFrame, profile: Profile, prompt: str = "base", temperature: Column | float = 0.7, attempt: Column | int = 0, seed: str = "sim", easing: dict[str, tuple] = EASE) -> DataFrame:
    """A generator's answers: qa has qa_id, instruction, reference (the right answer), input, alien and alien_ask. Adds answer and asked.

    Draws are hashes of (seed, id, prompt, temperature, attempt): every arm of an experiment sees the same generator. `easing` says by how much a
    prompt lowers the chance of each fault; with EASE the prompts help by construction, with NEUTRAL none does."""
    # drawn once, in a column of its own: damages ask for it again and again
    ask, out = damaged(F.col("fault"), {"instruction": F.col("instruction"), "output": F.col("reference"), "alien": F.col("alien"), "alien_ask": F.col("alien_ask")})
    return qa.withColumn("fault", drawn_fault(profile, prompt, temperature, attempt, seed, easing)).withColumns({"asked": ask, "answer": out})


#: What a simulated call may come to.
FAULTS = ("none", *INJECTIONS)


def drawn_fault(profile: Profile, prompt: str = "base", temperature: Column | float = 0.7, attempt: Column | int = 0, seed: str = "sim", easing: dict[str, tuple] = EASE) -> Column:
    """One of FAULTS, of the pair qa_id in this call."""
    t = F.lit(temperature) if not isinstance(temperature, Column) else temperature
    a = F.lit(attempt) if not isinstance(attempt, Column) else attempt
    draw = lambda what: tx.hash_unit(F.lit(seed), F.col("qa_id"), F.lit(prompt), F.lit(what), t, a)
    ease = easing[prompt]
    # a fault that belongs to the pair stays with it across attempts at the same prompt
    lasting = lambda what: tx.hash_unit(F.lit(seed), F.col("qa_id"), F.lit(what))
    drift = draw("drift") < F.lit(ease[0]) * (F.lit(profile.drift) + F.lit(profile.slope) * t)
    outside = lasting("parametric") < ease[1] * profile.parametric
    domain = lasting("domain") < ease[2] * profile.domain
    question = lasting("question") < ease[3] * profile.question
    return F.when(question, "instruction_quality").when(domain, "domain_mismatch").when(outside, "parametric_drift").when(drift, F.when(draw("way") < 0.5, "contradicts_source").otherwise("high_temperature_drift")).otherwise("none")


def preference_pairs(qa: DataFrame, mode: str = "two_pass", rejected_temperature: float = 1.2) -> DataFrame:
    """qa_id, chosen, rejected, calls. single_call: both from one call, the rejected one a shortened answer. two_pass: the rejected one from a second,
    hotter call, so further from the chosen one."""
    rows = other_source(qa)
    if mode == "single_call":
        weak = F.array_join(F.slice(tx.words(F.col("output")), 1, F.greatest(F.floor(tx.token_count(F.col("output")) * 0.6), F.lit(1)).cast("int")), " ")
        return rows.select("qa_id", "instruction", "input", F.col("output").alias("chosen"), weak.alias("rejected"), F.lit(1).alias("calls"))
    hot = F.when(tx.hash_unit(F.lit("hot"), F.col("qa_id")) < min(1.0, rejected_temperature / 2), F.col("alien")).otherwise(damaged(F.lit("parametric_drift"), {c: F.col(c) for c in ("instruction", "output", "alien", "alien_ask")})[1])
    return rows.select("qa_id", "instruction", "input", F.col("output").alias("chosen"), hot.alias("rejected"), F.lit(2).alias("calls"))


def rollouts(qa: DataFrame, k: int = 4, temperatures: tuple = (), spread: float = 0.6, scorer: Callable[[Column, Column, Column], Column] | None = None, base: float = 0.7) -> DataFrame:
    """qa_id, responses, reward_scores, temperatures, calls: k answers at given temperatures, or spread evenly around the base."""
    temps = tuple(temperatures) or tuple(round(base - spread / 2 + spread * j / max(k - 1, 1), 4) for j in range(k))
    rows = other_source(qa).withColumn("reference", F.col("output"))
    out, answers = rows, []
    for j, t in enumerate(temps):
        out = simulate(out, PROFILES["small"], temperature=t, attempt=j).withColumnRenamed("answer", f"a{j}").drop("asked", "fault")
        answers.append(F.col(f"a{j}"))
    scores = F.array(*[scorer(F.col("instruction"), a, F.col("input")) for a in answers]) if scorer else F.lit(None).cast("array<double>")
    return out.select("qa_id", "instruction", "input", F.array(*answers).alias("responses"), scores.alias("reward_scores"), F.array(*map(F.lit, temps)).alias("temperatures"), F.lit(len(temps) * (2 if scorer else 1)).alias("calls"))


def dialogues(qa: DataFrame, num_turns: int = 3, mode: str = "turn_by_turn") -> DataFrame:
    """qa_id, turns (role, content), calls. turn by turn: each question and answer is a call that sees all before it (2 * num_turns calls), so the next
    question takes up the last answer, and the next answer depends on it; single_call writes all at once, sentence after sentence."""
    s = tx.sentences(F.col("input"))
    first = lambda x: F.regexp_replace(F.array_join(F.slice(tx.words(x), 1, 3), " "), r"[.,;:!?]", "")
    at = lambda k: F.element_at(s, (F.pmod(k, F.greatest(F.size(s), F.lit(1))) + 1).cast("int"))
    rows, turns = qa.where(F.size(s) > 0).withColumn("_a0", F.col("output")), []
    for j in range(num_turns):
        if j:
            told = at(tx.hash_int(1 << 20, F.col(f"_a{j - 1}"), F.lit(j))) if mode == "turn_by_turn" else at(F.lit(j))
            rows = rows.withColumn(f"_a{j}", told)
        ask = F.col("instruction") if not j else F.concat(F.lit("And after "), first(F.col(f"_a{j - 1}")), F.lit(", what of "), first(F.col(f"_a{j}")), F.lit("?")) if mode == "turn_by_turn" else F.concat(F.lit("And what about "), first(F.col(f"_a{j}")), F.lit("?"))
        turns += [F.struct(F.lit("user").alias("role"), ask.alias("content")), F.struct(F.lit("assistant").alias("role"), F.col(f"_a{j}").alias("content"))]
    return rows.select("qa_id", F.array(*turns).alias("turns"), F.lit(2 * num_turns if mode == "turn_by_turn" else 1).alias("calls"))


EVOLUTIONS = {"constraints": " Answer in at most two sentences.", "deepen": " Explain why as well.", "concretise": " Give one example from the passage.", "reasoning": " Show each step of your reasoning.", "broaden": " Name a related matter in the passage."}


def evolve(qa: DataFrame, strategies: tuple = tuple(EVOLUTIONS), answer: bool = False) -> DataFrame:
    """qa_id, strategy, instruction, output, calls: one evolved instruction a strategy, with an answer pass if asked for."""
    pairs = F.array(*[F.struct(F.lit(s).alias("strategy"), F.lit(EVOLUTIONS[s]).alias("more")) for s in strategies])
    rows = qa.withColumn("e", F.explode(pairs))
    return rows.select("qa_id", F.col("e.strategy").alias("strategy"), F.concat("instruction", F.col("e.more")).alias("instruction"), (F.col("output") if answer else F.lit(None).cast("string")).alias("output"), F.lit(1 + answer).alias("calls"))


def chain_of_thought(qa: DataFrame, mode: str = "generate") -> DataFrame:
    """qa_id, output, calls. generate: reasoning and an answer found anew; wrap: reasoning before the answer that is there."""
    why = F.concat(F.lit("The passage says: "), F.element_at(tx.sentences(F.col("input")), 1), F.lit("\nSo: "))
    answer = F.col("output") if mode == "wrap" else F.element_at(tx.sentences(F.col("output")), 1)
    return qa.where(F.size(tx.sentences(F.col("input"))) > 0).select("qa_id", "instruction", F.concat(why, answer).alias("output"), F.lit(1).alias("calls"))


# ---- networked backends and the ledger --------------------------------------------------------------------------------------


class Backend:
    """generate(prompt, temperature) -> dict(text, model, prompt_tokens, completion_tokens, latency); raises on failure."""

    model = "none"

    def generate(self, prompt: str, temperature: float) -> dict:
        raise NotImplementedError

    async def agenerate(self, prompt: str, temperature: float) -> dict:
        import asyncio

        return await asyncio.to_thread(self.generate, prompt, temperature)


class HttpBackend(Backend):
    """A chat-completions endpoint over HTTP, local or routed, with exponential backoff; thinking blocks are cut out."""

    def __init__(self, base: str, model: str, key: str | None = None, extra: dict | None = None, retries: int = 3, backoff: float = 0.5, strip_think: bool = True):
        self.base, self.model, self.key, self.extra, self.retries, self.backoff, self.strip = base.rstrip("/"), model, key, extra or {}, retries, backoff, strip_think

    def generate(self, prompt: str, temperature: float) -> dict:
        import json
        import re
        import urllib.request

        body = {"model": self.model, "messages": [{"role": "user", "content": prompt}], "temperature": temperature} | self.extra
        head = {"Content-Type": "application/json"} | ({"Authorization": f"Bearer {self.key}"} if self.key else {})
        for k in range(self.retries + 1):
            began = time.time()
            try:
                with urllib.request.urlopen(urllib.request.Request(f"{self.base}/chat/completions", json.dumps(body).encode(), head), timeout=120) as r:
                    said = json.load(r)
                text = said["choices"][0]["message"]["content"]
                text = re.sub(r"(?s)<think>.*?</think>", "", text).strip() if self.strip else text
                use = said.get("usage", {})
                return {"text": text, "model": self.model, "prompt_tokens": use.get("prompt_tokens", 0), "completion_tokens": use.get("completion_tokens", 0), "latency": time.time() - began}
            except OSError:
                if k == self.retries:
                    raise
                time.sleep(self.backoff * 2**k)
        raise AssertionError("unreachable")


LEDGER = "call_id string, text string, model string, prompt_tokens long, completion_tokens long, latency double, error string"


def call_id(model: str, prompt: Column, temperature: Column, attempt: Column) -> Column:
    return F.sha2(F.concat_ws("\x1f", F.lit(model), prompt, temperature.cast("string"), attempt.cast("string")), 256)


def run_calls(calls: DataFrame, backend: Backend, ledger_dir: str, concurrency: int = 8, partitions: int | None = None, budget: int | None = None) -> DataFrame:
    """calls: call_id, prompt, temperature. Calls that the ledger has are not made again; new ones run `concurrency` at a time in each task, and are written
    to the ledger before anything reads them. Returns the ledger's rows of these calls. More new calls than `budget` raise before the first is made."""
    spark = calls.sparkSession
    p = spark._jvm.org.apache.hadoop.fs.Path(ledger_dir)
    there = p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)
    wanted = calls.select("call_id", "prompt", F.col("temperature").cast("double").alias("temperature")).dropDuplicates(["call_id"])
    todo = wanted.join(spark.read.schema(LEDGER).parquet(ledger_dir).where("error is null").select("call_id"), "call_id", "left_anti") if there else wanted

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import asyncio

        async def all_of(rows):
            gate = asyncio.Semaphore(concurrency)

            async def one(row):
                async with gate:
                    try:
                        r = await backend.agenerate(row["prompt"], row["temperature"])
                        return {"call_id": row["call_id"], "error": None} | r
                    except Exception as e:  # a failed call is a row with its error, not a lost record
                        return {"call_id": row["call_id"], "text": None, "model": backend.model, "prompt_tokens": 0, "completion_tokens": 0, "latency": 0.0, "error": str(e)[:500]}

            return await asyncio.gather(*map(one, rows))

        for b in batches:
            done = asyncio.run(all_of(b.to_pylist()))
            names = [c.split()[0] for c in LEDGER.split(", ")]
            kinds = [pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array([d[n] for d in done], t) for n, t in zip(names, kinds)], names=names)

    todo = materialize(todo, "calls")  # fixed before the first call is made
    if budget is not None and (n := todo.count()) > budget:
        raise ValueError(f"{n} calls are needed and {budget} are allowed (call_budget)")
    todo.repartition(partitions or spark.sparkContext.defaultParallelism, "call_id").mapInArrow(run, LEDGER).write.mode("append").parquet(ledger_dir)
    rows = spark.read.schema(LEDGER).parquet(ledger_dir)
    return rows.join(wanted.select("call_id"), "call_id", "left_semi").groupBy("call_id").agg(F.min_by(F.struct(*[F.col(c.split()[0]) for c in LEDGER.split(", ")[1:]]), F.col("error").isNotNull()).alias("r")).select("call_id", "r.*")


@dataclass(frozen=True)
class GenerationTask:
    """A task is a way to build a prompt and a way to read the answer; parse gives a value or null for an answer that can't be read."""

    build: Callable[[], Column]
    parse: Callable[[Column], Column]


def run_task(df: DataFrame, task: GenerationTask, backend: Backend, ledger_dir: str, temperature: float = 0.7, parse_retries: int = 1, concurrency: int = 8, budget: int | None = None) -> DataFrame:
    """Adds generated, raw_response and call (the answer's model, tokens and latency) to every row; generated is null where all attempts couldn't be
    read: `rejected_answers` makes records of those."""
    rows = df.withColumn("_prompt", task.build())
    done = None
    left = rows
    for attempt in range(parse_retries + 1):
        calls = left.withColumn("call_id", call_id(backend.model, F.col("_prompt"), F.lit(temperature), F.lit(attempt))).withColumn("temperature", F.lit(temperature))
        answers = run_calls(calls.select("call_id", F.col("_prompt").alias("prompt"), "temperature"), backend, ledger_dir, concurrency, budget=budget)
        got = materialize(calls.join(answers.select("call_id", F.col("text").alias("raw_response"), F.create_map(F.lit("model"), "model", F.lit("prompt_tokens"), F.col("prompt_tokens").cast("string"), F.lit("completion_tokens"), F.col("completion_tokens").cast("string"), F.lit("latency"), F.round("latency", 3).cast("string")).alias("call")), "call_id", "left").drop("call_id", "temperature").withColumn("generated", task.parse(F.col("raw_response"))), "answers")
        good = got.where("generated is not null") if attempt < parse_retries else got
        done = good if done is None else done.unionByName(good)
        left = got.where("generated is null").drop("raw_response", "generated", "call")
    return done.drop("_prompt")
