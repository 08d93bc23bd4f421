"""Line-first quality rules: judge each line, remove the failures, then reject documents that lose too much text.

A line (split at \\n) that has a word fails when it is one of
- navigation: its `|`, `»` or `>` separators are at least a third of its words;
- symbol noise: at least three tenths of its words hold one of # * $ % & | < >;
- stutter: over half of its words (of at least six) equal the word before them;
- a repeat: an earlier line of the document says the same;
- boilerplate: it starts or ends as a site notice (cookie, privacy, rights, subscription phrases), on a short line;
- unfinished: no sentence mark in it at all and three words or fewer, on a document of ten lines or more.
A document is rejected when the removed lines hold more than 30 % of its words, or when it fails the base rules (fewer
than 50 words, or over half of its words in repeated windows of three).

Runs in mapInArrow, a document at a time, so memory is bounded by the longest text; no shuffle. Defined results: a null
or empty text has no words, so every count is 0, base_failed is true and kept false. Repeated rows are judged each.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from refinery.llm.common import WORD_RE

SYMBOLS = "#*$%&|<>"
SYMBOL = re.compile(r"[#*$%&|<>]")
SEPARATORS = frozenset(("|", "»", ">", "/", "·", "•"))
#: Phrases of site notices that begin a line, in English, German, French and Spanish; and those that may end one.
NOTICES = (
    r"we use cookies|this (web)?site uses cookies|accept (all )?cookies|privacy policy|terms of (use|service)|all rights reserved|copyright (©|\(c\))|©|subscribe to|sign up (for|to)|log ?in|share (this|on)|follow us|read more|click here|skip to (main )?content|back to top|javascript is",
    r"wir verwenden cookies|diese (web)?seite verwendet cookies|alle cookies akzeptieren|datenschutzerklärung|nutzungsbedingungen|alle rechte vorbehalten|newsletter abonnieren|jetzt (anmelden|registrieren)|folgen sie uns|weiterlesen|hier klicken|zum inhalt springen|nach oben",
    r"nous utilisons des cookies|ce site utilise des cookies|accepter (tous )?les cookies|politique de confidentialité|conditions d.utilisation|tous droits réservés|abonnez-vous|inscrivez-vous|partager (sur|cet article)|suivez-nous|lire la suite|cliquez ici|aller au contenu|retour en haut",
    r"(usamos|utilizamos) cookies|este sitio (web )?(usa|utiliza) cookies|aceptar (todas )?las cookies|política de privacidad|(términos|condiciones) de uso|todos los derechos reservados|suscríbete|regístrate|compartir en|síguenos|leer más|haz clic aquí|ir al contenido|volver arriba",
)
CLOSINGS = r"all rights reserved|privacy policy|terms of (use|service)|alle rechte vorbehalten|tous droits réservés|todos los derechos reservados"
BOILERPLATE = re.compile(rf"^\W*({'|'.join(NOTICES)})|({CLOSINGS})\W*$", re.I)
SENTENCE_MARK = re.compile(r"[.!?…:;\"”»]")
#: Fixed values of the base rules and of the method.
MIN_WORDS, MAX_REPEAT_PERCENT, MAX_LOST = 50, 50, 0.3
NOISE_SHARE, NAV_SHARE, STUTTER_SHARE, STUTTER_WORDS, NOTICE_WORDS = 0.3, 1 / 3, 0.5, 6, 25


def repeat_words(words: list[str]) -> int:
    """Words inside three-word windows that occur twice or more in the text, first included."""
    n = len(words)
    if n < 4:
        return 0
    ids: dict[str, int] = {}
    codes = np.array([ids.setdefault(w, len(ids)) for w in words], dtype=np.int64)
    k = len(ids)
    pair = np.unique(codes[:-1] * k + codes[1:], return_inverse=True)[1].astype(np.int64)
    _, where, times = np.unique(pair[:-1] * k + codes[2:], return_inverse=True, return_counts=True)
    hit = times[where] > 1
    covered = np.zeros(n, dtype=bool)
    for shift in range(3):
        covered[shift : n - 2 + shift] |= hit
    return int(covered.sum())


def line_fault(line: str, words: list[str], seen: set[str], n_lines: int) -> str | None:
    """The first rule that a line with words fails."""
    n = len(words)
    if line in seen:
        return "repeat"
    if SYMBOL.search(line):
        if n >= 3 and sum(w in SEPARATORS for w in words) >= NAV_SHARE * n:
            return "navigation"
        if sum(1 for w in words if SYMBOL.search(w)) >= NOISE_SHARE * n:
            return "noise"
    if n >= STUTTER_WORDS:
        low = " ".join(words).lower().split(" ")
        if 2 * sum(map(eq, low, low[1:])) >= STUTTER_SHARE * n:
            return "stutter"
    if n <= NOTICE_WORDS and BOILERPLATE.search(line):
        return "boilerplate"
    if n <= 3 and n_lines >= 10 and not SENTENCE_MARK.search(line):
        return "unfinished"
    return None


def judge(text: str | None) -> tuple[dict, str]:
    """Counts and verdict of one text, and the text without its failed lines."""
    text = text or ""
    lines = text.split("\n")
    words: list[str] = []
    seen: set[str] = set()
    n_dup = lost = bad = 0
    good = []
    for line in lines:
        found = WORD_RE.findall(line)
        if not found:
            good.append(line)
            continue
        fault = line_fault(line, found, seen, len(lines))
        n_dup += line in seen
        seen.add(line)
        words += found
        if fault:
            lost, bad = lost + len(found), bad + 1
        else:
            good.append(line)
    n = len(words)
    repeated = repeat_words(words)
    failed = n < MIN_WORDS or 100 * repeated > MAX_REPEAT_PERCENT * n
    # every blank but \n splits words inside lines as in the whole text, so the lines' words are the text's words
    return {
        "n_words": n,
        "word_chars": sum(map(len, words)),
        "n_symbols": sum(map(text.count, SYMBOLS)),
        "n_dup_lines": n_dup,
        "n_repeat_words": repeated,
        "base_failed": failed,
        "kept": not failed and lost <= MAX_LOST * n,
        "n_bad_lines": bad,
        "lost_words": lost,
    }, "\n".join(good)


SCHEMA = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, n_bad_lines long, lost_words long"


def assess(docs: DataFrame, with_text: bool = False) -> DataFrame:
    """doc_id and the columns of SCHEMA for every row; with_text adds cleaned_text."""
    names = [c.split()[0] for c in SCHEMA.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, cleaned = [], []
            for t in b.column(1):
                counts, good = judge(t.as_py())
                rows.append(counts)
                if with_text:
                    cleaned.append(good)
            arrays = [b.column(0), *(pa.array([r[k] for r in rows], pa.bool_() if k in ("base_failed", "kept") else pa.int64()) for k in names)]
            yield pa.RecordBatch.from_arrays(arrays + [pa.array(cleaned, pa.string())] * with_text, names=["doc_id", *names] + ["cleaned_text"] * with_text)

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text"))
    return rows.mapInArrow(run, f"doc_id long, {SCHEMA}" + ", cleaned_text string" * with_text)


def keep_good(docs: DataFrame) -> DataFrame:
    """The rows of docs that are kept, their text without the failed lines (n_chars with it, where docs has one), other columns as they
    came. A filter in the same pass: no join by id."""
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            k = b.schema.get_field_index("text")
            judged = [judge(t.as_py()) for t in b.column(k)]
            kept = pa.array([counts["kept"] for counts, _ in judged], pa.bool_())
            texts = [good for counts, good in judged if counts["kept"]]
            b = b.filter(kept)
            b = b.set_column(k, b.schema.field(k), pa.array(texts, pa.string()).cast(b.schema.field(k).type))
            if "n_chars" in b.schema.names:
                n = b.schema.get_field_index("n_chars")
                b = b.set_column(n, b.schema.field(n), pa.array([len(t) for t in texts], pa.int64()).cast(b.schema.field(n).type))
            yield b

    return docs.mapInArrow(run, schema)


ORACLE = r"""
with w as (select doc_id, row_number() over () as row_id, coalesce(text, '') as text from documents),
t as (select doc_id, row_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as words, string_split(text, chr(10)) as lines from w),
x as (select row_id, unnest(words) as word, generate_subscripts(words, 1) as i from t),
g as (select row_id, i, word || ' ' || lead(word) over o || ' ' || lead(word, 2) over o as tri from x window o as (partition by row_id order by i)),
h as (select row_id, i from (select row_id, i, count(*) over (partition by row_id, tri) as n from g where tri is not null) where n > 1),
c as (select row_id, count(distinct i + k) as n_repeat from h, (values (0), (1), (2)) as s(k) group by row_id),
l0 as (select row_id, unnest(lines) as line, generate_subscripts(lines, 1) as ln, len(lines) as n_lines from t),
l1 as (select row_id, line, n_lines, regexp_extract_all(line, '[^\x20\x09-\x0D]+') as ws, row_number() over (partition by row_id, line order by ln) > 1 as again from l0 where regexp_matches(line, '[^\x20\x09-\x0D]')),
l2 as (select row_id, line, n_lines, again, len(ws) as n, len(list_filter(ws, lambda v: v in ('|', '»', '>', '/', '·', '•'))) as seps,
  len(list_filter(ws, lambda v: regexp_matches(v, '[#*$%&|<>]'))) as syms, len(list_filter(range(1, len(ws)), lambda k: lower(ws[k]) = lower(ws[k + 1]))) as twice from l1),
l3 as (select row_id, n, again, again or (syms > 0 and n >= 3 and seps >= n * (1.0::double / 3)) or (syms > 0 and syms >= 0.3::double * n) or (n >= 6 and 2 * twice >= 0.5 * n)
  or (n <= 25 and regexp_matches(line, '(?i)^[^\pL\pN_]*(@notices@)|(@closings@)[^\pL\pN_]*$'))
  or (n <= 3 and n_lines >= 10 and not regexp_matches(line, '[.!?…:;"”»]')) as bad from l2),
l as (select row_id, sum(case when bad then n else 0 end) as lost, sum(again::int) as dup from l3 group by row_id)
select doc_id, len(words)::bigint as n_words, coalesce(list_sum(list_transform(words, lambda v: length(v))), 0)::bigint as word_chars, len(regexp_extract_all(text, '[#*$%&|<>]'))::bigint as n_symbols,
  coalesce(dup, 0)::bigint as n_dup_lines, coalesce(n_repeat, 0)::bigint as n_repeat_words, len(words) < 50 or 100 * coalesce(n_repeat, 0) > 50 * len(words) as base_failed,
  not (len(words) < 50 or 100 * coalesce(n_repeat, 0) > 50 * len(words)) and coalesce(lost, 0) <= 0.3::double * len(words) as kept
from t left join c using (row_id) left join l using (row_id)
""".replace("@notices@", "|".join(NOTICES)).replace("@closings@", CLOSINGS)
