"""Hygiene, cheapest gate first: secrets (reject), personal data (replace), toxicity (reject, judge in the middle band)."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from refinery.config import CLINICAL_PII, DEFAULT_PII
from refinery.functions import text as tx
from refinery.operators.storage import materialize
from refinery.records import append_provenance, reject, undecided

#: Text fields to scan, by task type.
SCANNED = {"preference": ("instruction", "input", "chosen", "rejected"), "language_modeling": ("output",), "grpo": ("instruction", "input")}
ALL_FIELDS = ("instruction", "input", "output", "chosen", "rejected")


def scan_text(fields: tuple | None = None) -> Column:
    """The texts of a record that the gates read, joined by line ends: chosen by task type, or as given."""
    joined = lambda names: F.concat_ws("\n", *[F.col(n) for n in names])
    if fields:
        return joined(fields)
    out = joined(("instruction", "input", "output"))
    for kind, names in SCANNED.items():
        texts = joined(names) if kind != "grpo" else F.concat_ws("\n", joined(names), F.concat_ws("\n", F.coalesce("responses", F.array())))
        out = F.when(F.col("task_type") == kind, texts).otherwise(out)
    return out


#: Shapes of credentials.
SECRET_PATTERNS = {
    "aws_key": r"\b(AKIA|ASIA)[0-9A-Z]{16}\b",
    "git_token": r"\bgh[pousr]_[A-Za-z0-9]{36}\b",
    "private_key": r"-----BEGIN [A-Z ]*PRIVATE KEY-----",
    "jwt": r"\beyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}",
    "saas_token": r"\b(xox[baprs]-[0-9A-Za-z-]{10,}|sk_live_[0-9A-Za-z]{16,}|AIza[0-9A-Za-z_-]{35})",
}
KEYWORD = r"(?i)\b(password|passwd|secret|api_?key|token)\b\s*[:=]\s*\S+"
QUOTED_HEX, BARE_HEX = r"[\"']([0-9a-fA-F]{16,})[\"']", r"\b([0-9a-fA-F]{16,})\b"
QUOTED_B64, BARE_B64 = r"[\"']([A-Za-z0-9+/_=-]{20,})[\"']", r"\b([A-Za-z0-9+/_=-]{20,})\b"


def high_entropy(text: Column, pattern: str, limit: float, skip: str | None = None) -> Column:
    """How many distinct matches of a pattern exceed an entropy limit."""
    found = F.array_distinct(F.regexp_extract_all(text, F.lit(pattern), F.lit(1)))
    return F.size(F.filter(found, lambda x: (tx.shannon_entropy(x) > limit) & (~x.rlike(skip) if skip else F.lit(True))))


def secret_counts(text: Column, hex_limit: float = 3.0, base64_limit: float = 4.5, quoted_only: bool = True, code_mode: bool = False) -> Column:
    """Map from detector to number of hits, detectors without hits left out."""
    text = F.coalesce(text, F.lit(""))
    counts = {name: F.regexp_count(text, F.lit(p)) for name, p in SECRET_PATTERNS.items()}
    counts["hex_entropy"] = high_entropy(text, QUOTED_HEX if quoted_only else BARE_HEX, hex_limit)
    counts["base64_entropy"] = high_entropy(text, QUOTED_B64 if quoted_only else BARE_B64, base64_limit, skip="^[0-9a-fA-F]+$")
    if code_mode:
        counts["keyword"] = F.regexp_count(text, F.lit(KEYWORD))
    return F.map_filter(F.create_map(*[x for k, v in counts.items() for x in (F.lit(k), v)]), lambda k, v: v > 0)


def secrets_gate(df: DataFrame, hex_limit: float = 3.0, base64_limit: float = 4.5, quoted_only: bool = True, code_mode: bool = False, fields: tuple | None = None, mode: str = "reject", config_hash: str = "", ts: str = "1970-01-01T00:00:00Z") -> DataFrame:
    """Rejects records that hold a credential; the reason lists the detectors, provenance their counts, neither the secret.
    mode redact is the ablation that masks shapes instead."""
    df = df.withColumn("_hits", secret_counts(scan_text(fields), hex_limit, base64_limit, quoted_only, code_mode))
    df = append_provenance(df, "secrets_gate", config_hash, ts, {"hits": F.to_json("_hits")}, when=F.size("_hits") > 0)
    if mode == "redact":
        for f in ALL_FIELDS:
            c = F.col(f)
            for p in (*SECRET_PATTERNS.values(), QUOTED_HEX):
                c = F.regexp_replace(c, p, "[secret]")
            df = df.withColumn(f, c)
        return df.drop("_hits")
    return reject(df, F.size("_hits") > 0, "secrets", "secrets_gate", F.array_join(F.array_sort(F.map_keys("_hits")), ",")).drop("_hits")


#: Shape, base score and score after its checksum or context of each entity type.
PII_PATTERNS = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}", 1.0),
    "phone": (r"\+\d{1,3} \(\d{3}\) \d{3}-\d{4}|\(\d{3}\) \d{3}-\d{4}", 0.75),
    "us_ssn": (r"\b\d{3}-\d{2}-\d{4}\b", 0.85),
    "credit_card": (r"\b\d{16}\b|\b\d{4}[ -]\d{4}[ -]\d{4}[ -]\d{4}\b", 0.3),
    "ip_address": (r"\b(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)\b", 0.95),
    "us_bank": (r"(?i)\baccount (?:number |no\.? )?(\d{8,17})\b", 0.75),
    "iban": (r"\b[A-Z]{2}\d{2}[A-Z0-9]{11,30}\b", 0.5),
    "person": (r"\b(?:Mr|Mrs|Ms|Dr|Prof)\. [A-Z][a-z]+(?: [A-Z][a-z]+)?", 0.85),
    "date_time": (r"\b\d{4}-\d{2}-\d{2}\b|\b\d{1,2}/\d{1,2}/\d{4}\b", 0.75),
    "location": (r"\b\d{1,5} [A-Z][a-z]+ (?:Street|Avenue|Road|Lane)\b", 0.75),
    "medical_licence": (r"\b[A-Z]{2}\d{7}\b", 0.7),
}


def iban_valid(x: Column) -> Column:
    """The mod-97 test: first four characters last, letters as two digits, remainder 1."""
    turned = F.concat(F.substr(x, F.lit(5)), F.substring(x, 1, 4))
    return F.aggregate(tx.chars(turned), F.lit(0), lambda a, c: F.when(c.rlike("[0-9]"), (a * 10 + c.cast("int")) % 97).otherwise((a * 100 + F.ascii(c) - 55) % 97)) == 1


def pii_score(kind: str, value: Column) -> Column:
    base = F.lit(PII_PATTERNS[kind][1])
    if kind == "credit_card":
        return F.when(tx.luhn(F.regexp_replace(value, "[ -]", "")), 1.0).otherwise(base)
    if kind == "iban":
        return F.when(iban_valid(value), 1.0).otherwise(base)
    return base


def _fake(kind: str, k: Column) -> Column:
    digits = lambda n, salt="": F.substring(F.translate(F.md5(F.concat(k.cast("string"), F.lit(salt))), "abcdef", "123456"), 1, n)
    names = F.array(*map(F.lit, "Alder Birch Cedar Elm Fir Hazel Juniper Larch Maple Oak Pine Rowan Spruce Willow Yew Aspen".split()))
    return {
        "email": F.concat(F.lit("user"), k.cast("string"), F.lit("@example.org")),
        "phone": F.concat(F.lit("+1 (555) "), digits(3), F.lit("-"), F.lpad((k % 10000).cast("string"), 4, "0")),
        "us_ssn": F.concat(F.lit("900-"), F.lpad((F.floor(k / 10000) % 100).cast("string"), 2, "0"), F.lit("-"), F.lpad((k % 10000).cast("string"), 4, "0")),
        "credit_card": F.concat(F.lit("4000"), F.lpad(k.cast("string"), 12, "0")),
        "ip_address": F.concat(F.lit("10."), (F.floor(k / 65536) % 256).cast("string"), F.lit("."), (F.floor(k / 256) % 256).cast("string"), F.lit("."), (k % 256).cast("string")),
        "us_bank": F.concat(F.lit("account 9"), F.lpad(k.cast("string"), 11, "0")),
        "iban": F.concat(F.lit("XX00TEST"), F.lpad(k.cast("string"), 12, "0")),
        "person": F.concat(F.lit("Mx. "), F.element_at(names, (k % 16 + 1).cast("int")), F.lit(" "), F.element_at(names, (F.floor(k / 16) % 16 + 1).cast("int")), F.translate(F.floor(k / 256).cast("string"), "0123456789", "abcdefghij")),
        "date_time": F.date_add(F.lit("1950-01-01").cast("date"), (k % 20000).cast("int")).cast("string"),
        "location": F.concat((k % 900 + 100).cast("string"), F.lit(" Example Street")),
        "medical_licence": F.concat(F.lit("ZZ"), F.lpad((k % 10000000).cast("string"), 7, "0")),
    }[kind]


def _scored(kind: str):
    return lambda v: F.struct(F.lit(kind).alias("type"), v.alias("value"), pii_score(kind, v).alias("score"))


def pii_findings(text: Column, entities: tuple = DEFAULT_PII, threshold: float = 0.7) -> Column:
    """Distinct findings of a text: array of struct(type, value, score), in order of type and value, at or above the threshold."""
    found = []
    for kind in entities:
        values = F.array_sort(F.array_distinct(F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(PII_PATTERNS[kind][0]), F.lit(0))))
        found.append(F.filter(F.transform(values, _scored(kind)), lambda s: s["score"] >= threshold))
    return F.concat(*found)


def pseudonymize(df: DataFrame, entities: tuple = DEFAULT_PII, threshold: float = 0.7, seed: int = 0, mode: str = "pseudonym", fields: tuple | None = None, config_hash: str = "", ts: str = "1970-01-01T00:00:00Z") -> DataFrame:
    """Replaces each entity by a fake of its kind, the same in all fields of a record and different in the next record.

    A fake is a function of (seed, record id, type) and the entity's rank within the record, so no two of a record meet. mode mask
    writes the type instead. Provenance holds counts of types, never values."""
    names = fields or ALL_FIELDS
    whole = F.concat_ws("\n", *[F.col(f) for f in names], F.concat_ws("\n", F.coalesce("responses", F.array())))
    df = df.withColumn("_found", pii_findings(whole, entities, threshold))
    base = lambda kind: tx.hash_int(1_000_000, F.lit(seed), F.col("id"), F.lit(kind))

    def fake(s: Column, k: Column) -> Column:
        if mode == "mask":
            return F.concat(F.lit("<"), s["type"], F.lit(">"))
        out = F.lit(None).cast("string")
        for kind in entities:
            out = F.when(s["type"] == kind, _fake(kind, base(kind) + k)).otherwise(out)
        return out

    pairs = F.transform("_found", lambda s, k: F.struct(F.length(s["value"]).alias("n"), s["value"].alias("value"), fake(s, k).alias("fake")))
    df = df.withColumn("_pairs", F.reverse(F.array_sort(pairs)))  # longest first: no value inside another is cut
    swap = lambda c: F.aggregate("_pairs", c, lambda t, p: F.replace(t, p["value"], p["fake"]))
    df = df.withColumns({f: swap(F.col(f)) for f in names} | {"responses": F.transform("responses", swap)})
    counts = F.to_json(F.aggregate(F.array(*map(F.lit, entities)), F.create_map().cast("map<string,int>"), lambda m, e: F.when(F.exists("_found", lambda s: s["type"] == e), F.map_concat(m, F.create_map(e, F.size(F.filter("_found", lambda s: s["type"] == e))))).otherwise(m)))
    return append_provenance(df, "pseudonymize", config_hash, ts, {"entities": counts}, when=F.size("_found") > 0).drop("_found", "_pairs")


#: Weight of a lexicon word on each of six dimensions, by scorer variant.
DIMENSIONS = ("toxicity", "severe_toxicity", "obscene", "threat", "insult", "identity_attack")
VARIANTS = {"unbiased": (0.6, 0.2, 0.3, 0.1, 0.6, 0.1), "original": (0.8, 0.3, 0.4, 0.2, 0.7, 0.2), "multilingual": (0.6, 0.2, 0.3, 0.1, 0.5, 0.1)}


def learn_lexicon(texts: DataFrame, min_support: int = 3, min_precision: float = 0.8, min_share: float = 0.02) -> DataFrame:
    """texts: text, toxic (0/1), the training half. Words that are in at least min_support texts and in min_share of the toxic ones, and mostly in toxic ones:
    word, precision. The share keeps chance words out however many texts there are."""
    w = texts.select("toxic", F.explode(F.array_distinct(tx.words(F.regexp_replace(F.lower("text"), r"[.,;:!?\"]", "")))).alias("word"))
    least = max(min_support, math.ceil(min_share * texts.where("toxic = 1").count()))
    n, hits = F.count(F.lit(1)), F.sum("toxic")
    return w.groupBy("word").agg(n.alias("n"), hits.alias("hits")).where((F.col("hits") >= least) & (F.col("hits") >= min_precision * F.col("n"))).select("word", (F.col("hits") / F.col("n")).alias("precision"))


def toxicity_scores(df: DataFrame, lexicon: DataFrame, variant: str = "unbiased", text: Column | None = None, broadcast_rows: int = 100_000) -> DataFrame:
    """Adds toxicity: the greatest of six dimension scores, each 1 - (1 - weight)^hits over distinct lexicon words in the text."""
    words = df.select(F.col("id").alias("_id"), F.explode(F.array_distinct(tx.words(F.regexp_replace(F.lower(scan_text() if text is None else text), r"[.,;:!?\"]", "")))).alias("word"))
    lexicon = materialize(lexicon.select("word"), "lexicon")
    few = lexicon.count() <= broadcast_rows
    hits = words.join(F.broadcast(lexicon) if few else lexicon, "word", "left_semi").groupBy("_id").agg(F.count(F.lit(1)).alias("_hits"))
    out = df.join(hits, F.col("id") == F.col("_id"), "left").withColumn("_hits", F.coalesce("_hits", F.lit(0)))
    score = F.greatest(*[1 - F.pow(F.lit(1 - w), F.col("_hits")) for w in VARIANTS[variant]])
    return out.withColumn("toxicity", score).drop("_id", "_hits")


def toxicity_gate(df: DataFrame, lexicon: DataFrame, pass_below: float = 0.1, reject_above: float = 0.5, variant: str = "unbiased", judge: Callable[[DataFrame], DataFrame] | None = None, judge_reject: float = 0.5, fields: tuple | None = None) -> DataFrame:
    """Below pass_below: accepted. Above reject_above: rejected. Between: a judge (DataFrame to DataFrame with judge_score) sees only that band,
    in a branch of its own; without a judge the band is accepted."""
    live = materialize(toxicity_scores(df, lexicon, variant, scan_text(fields) if fields else None), "toxicity")
    live = reject(live, F.col("toxicity") > reject_above, "toxic_classifier", "toxicity_gate", F.format_string("%.2f", F.col("toxicity")))
    if judge is None:
        return live
    band = (F.col("status") == "accepted") & (F.col("toxicity") >= pass_below) & (F.col("toxicity") <= reject_above)
    judged = reject(judge(live.where(band)), F.col("judge_score") >= judge_reject, "toxic_judge", "toxicity_gate", F.format_string("%.2f", F.col("judge_score")))
    return live.where(~band).unionByName(judged.drop("judge_score"))


def hygiene(df: DataFrame, lexicon: DataFrame, cfg) -> tuple[DataFrame, DataFrame]:
    """Secrets, then personal data, then toxicity; each sees only what the gates before it left. Also a table gate, invoked, avoided, rejected."""
    n = df.count()
    one = materialize(secrets_gate(df, cfg.secrets_hex_limit, cfg.secrets_base64_limit, cfg.secrets_quoted_only, cfg.secrets_code_mode, cfg.secrets_fields, cfg.secrets_mode, cfg.digest(), cfg.run_ts), "secrets")
    gone, live = one.where("status = 'rejected'"), undecided(one)
    two = materialize(pseudonymize(live, cfg.pii_entities, cfg.pii_threshold, cfg.pii_seed, cfg.pii_mode, cfg.pii_fields, cfg.digest(), cfg.run_ts) if cfg.pii else live, "pii")
    three = materialize(toxicity_gate(two, lexicon, cfg.toxicity_pass, cfg.toxicity_reject, cfg.toxicity_scorer).drop("toxicity"), "toxic")
    n_secret = gone.count()
    n_toxic = three.where("status = 'rejected'").count()
    report = df.sparkSession.createDataFrame([("secrets", n, 0, n_secret), ("pii", n - n_secret, n_secret, 0), ("toxicity", n - n_secret, n_secret, n_toxic)], "gate string, invoked long, avoided long, rejected long")
    return gone.unionByName(three), report


__all__ = ["CLINICAL_PII", "DEFAULT_PII", "hygiene", "pseudonymize", "secrets_gate", "toxicity_gate"]
