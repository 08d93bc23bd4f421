"""Language identification with hyperdimensional profiles.

Each letter has a random vector of +1/-1 (seeded by its code point). A letter n-gram is bound as the product of its
letters' vectors, each rolled by its place; a text is the bundle (sum) of its n-grams' vectors, and a language the bundle
of its training texts, each first divided by its number of n-grams so that a long text doesn't outweigh the others. A text gets the language
whose prototype, centred on the mean of all prototypes, has the largest cosine with it, centred alike.

Texts are encoded in mapInArrow: n-grams are counted per text, and each distinct n-gram's vector is built once
per task and kept while the bound on its table holds. Training sums (language, dimension) cells: its shuffle is
languages x dimensions per task, independent of the number of texts.

Defined results: a null text or one without letters gets `und` with score 0, also when no training text exists. Training texts
whose language is null are skipped. Equal cosines: the language first in code point order.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Dimensions, letters in an n-gram, n-gram vectors kept in a task (each 2 bytes a dimension).
DIMENSIONS, GRAM, KEPT = 512, 3, 60_000
SEED = 20_011
#: Bounds of the classes of length (n-grams of a text) within which texts are compared with training texts; the low quantile of these,
#: how many training texts a class needs, and the steps of a likeness.
LENGTHS, LOW, ENOUGH, STEPS = (64, 128, 256), 0.05, 20, 10_000


def letter_classes(text: str) -> np.ndarray:
    """Code points of the lower-cased text, runs of all but letters as one 0, with a 0 at either end."""
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    low = codes < 128
    letter = (codes >= 97) & (codes <= 122)
    if not low.all():
        others = np.unique(codes[~low])
        good = others[[chr(c).isalpha() for c in others]]
        letter |= np.isin(codes, good)
    codes = np.where(letter, codes, 0)
    keep = np.ones(len(codes), dtype=bool)
    keep[1:] = (codes[1:] != 0) | (codes[:-1] != 0)
    codes = codes[keep]
    return np.pad(codes.astype(np.int64), (int(not len(codes) or codes[0] != 0), int(len(codes) > 0 and codes[-1] != 0)))


class Encoder:
    def __init__(self, dimensions: int = DIMENSIONS, gram: int = GRAM):
        self.d, self.gram = dimensions, gram
        self.letters: dict[int, np.ndarray] = {}
        self.rows: dict[int, int] = {}
        self.table = np.empty((1024, dimensions), dtype=np.float32)

    def letter(self, code: int) -> np.ndarray:
        v = self.letters.get(code)
        if v is None:
            v = self.letters[code] = np.random.default_rng((SEED, code)).integers(0, 2, self.d).astype(np.int8) * 2 - 1
        return v

    def row(self, key: int) -> int:
        """Place of an n-gram's vector: its letters' vectors, rolled by their place, multiplied."""
        v, rest = np.ones(self.d, dtype=np.int8), key
        for k in range(self.gram):
            v = v * np.roll(self.letter(rest & 0x1FFFFF), k)
            rest >>= 21
        at = len(self.rows)
        if at == len(self.table):
            self.table = np.concatenate((self.table, np.empty_like(self.table)))
        self.table[at] = v
        self.rows[key] = at
        return at

    def grams(self, text: str | None) -> tuple[list[int], np.ndarray]:
        """Places of a text's distinct n-grams in the table, and their counts; empty without letters."""
        codes = letter_classes(text) if text else np.empty(0, dtype=np.int64)
        if not codes.any():
            return [], np.empty(0)
        n = max(1, len(codes) - self.gram + 1)
        keys = np.zeros(n, dtype=np.int64)
        for k in range(min(self.gram, len(codes))):
            keys |= codes[k : k + n] << (21 * k)
        keys, counts = np.unique(keys, return_counts=True)
        rows = self.rows
        return [rows[k] if k in rows else self.row(k) for k in keys.tolist()], counts

    def tidy(self) -> None:
        if len(self.rows) > KEPT:
            self.rows.clear()
            self.table = self.table[:1024].copy()

    def encode(self, text: str | None) -> np.ndarray | None:
        """The bundle of a text's n-grams; None without letters."""
        at, counts = self.grams(text)
        if not at:
            return None
        out = np.zeros(self.d, dtype=np.float64)
        for k in range(0, len(at), 4096):
            out += counts[k : k + 4096].astype(np.float32) @ self.table[at[k : k + 4096]]
        self.tidy()
        return out


def profiles(labelled: DataFrame) -> dict[str, np.ndarray]:
    """One vector a language from all rows (text, lang) whose lang isn't null. Its size: languages x dimensions."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, sums, shares = Encoder(), {}, {}

        def fold_in() -> None:
            for lang, share in shares.items():
                sums[lang] = sums.get(lang, 0) + share[: len(encoder.rows)] @ encoder.table[: len(encoder.rows)].astype(np.float64)
            shares.clear()
            encoder.tidy()

        for b in batches:
            for text, lang in zip(b.column("text"), b.column("lang").to_pylist()):
                at, counts = encoder.grams(text.as_py())
                if at:
                    share = shares.get(lang)
                    if share is None or len(share) < len(encoder.table):
                        share = shares[lang] = np.pad(share if share is not None else np.zeros(0), (0, len(encoder.table) - (0 if share is None else len(share))))
                    share[at] += counts / counts.sum()
                if len(encoder.rows) > KEPT:
                    fold_in()
        fold_in()
        for lang, v in sums.items():
            # fixed point: the sum then doesn't depend on the order of tasks
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(v)), pa.array(np.arange(len(v)), pa.int32()), pa.array(np.round(v * 2.0**30).astype(np.int64))], names=["lang", "k", "v"])

    rows = labelled.where("lang is not null").select("text", F.col("lang").cast("string").alias("lang")).mapInArrow(run, "lang string, k int, v long")
    cells = rows.groupBy("lang", "k").agg(F.sum("v").alias("v")).groupBy("lang").agg(F.sort_array(F.collect_list(F.struct("k", "v"))).alias("v")).select("lang", F.col("v.v").alias("v"))
    return {r.lang: np.array(r.v, dtype=np.float64) / 2.0**30 for r in cells.collect()}


class Classifier:
    """Prototypes centred on their mean; tells a text's language and score."""

    def __init__(self, known: dict[str, np.ndarray]):
        self.names = sorted(known)
        matrix = np.array([known[n] / max(np.linalg.norm(known[n]), 1e-12) for n in self.names]) if known else np.zeros((0, DIMENSIONS))
        self.centre = matrix.mean(axis=0) if len(self.names) > 1 else np.zeros(DIMENSIONS)
        self.matrix = matrix
        axes = matrix - self.centre
        self.axes = axes / np.maximum(np.linalg.norm(axes, axis=1, keepdims=True), 1e-12)

    def __call__(self, encoder: Encoder, text: str | None) -> tuple[str, float]:
        return self.judge(encoder.encode(text) if self.names else None)

    def likeness(self, v: np.ndarray, lang: str) -> float:
        """Cosine of a bundle with a language's prototype, neither centred: about 0 for what shares no n-grams with the language."""
        return float(self.matrix[self.names.index(lang)] @ v / max(np.linalg.norm(v), 1e-12))

    def judge(self, v: np.ndarray | None) -> tuple[str, float]:
        n = 0 if v is None else np.linalg.norm(v)
        if not n:
            return "und", 0.0
        v = v / n - self.centre
        cosines = self.axes @ v / max(np.linalg.norm(v), 1e-12)
        best = int(np.argmax(np.round(cosines, 9)))
        return self.names[best], float(min(1.0, max(0.0, (1 + cosines[best]) / 2)))


def predict(docs: DataFrame, known: dict[str, np.ndarray]) -> DataFrame:
    """doc_id, lang_pred and score for each row of docs (doc_id, text)."""
    classify = Classifier(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder()
        for b in batches:
            langs, scores = zip(*found) if (found := [classify(encoder, t.as_py()) for t in b.column("text")]) else ((), ())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def fold(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo parts. A null id falls in no part's remainder (null)."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(parts))


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score: learned from the rows that aren't held out."""
    held = F.coalesce(fold(F.col("doc_id"), 4) == 2, F.lit(False))
    known = profiles(docs.where(~held).select("text", "lang"))
    return predict(docs.select("doc_id", "text"), known).select("doc_id", held.alias("held_out"), "lang_pred", "score")


def length_class(text: str) -> int:
    return int(np.searchsorted(LENGTHS, len(letter_classes(text)), side="right"))


def low_likeness(labelled: DataFrame, known: dict[str, np.ndarray]) -> dict[tuple[str | None, int], float]:
    """(language, class of length): the LOW quantile of all training texts' likeness to their own language, in steps of 1 / STEPS, so that
    the table of values doesn't grow with the texts. Language None: over all. Classes of fewer than ENOUGH training texts are left out."""
    classify = Classifier(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder()
        for b in batches:
            found = []
            for text, lang in zip(b.column("text").to_pylist(), b.column("lang").to_pylist()):
                v = encoder.encode(text) if lang in known else None
                if v is not None:
                    found.append((lang, length_class(text), classify.likeness(v, lang)))
            langs, lengths, likes = zip(*found) if found else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(lengths, pa.int32()), pa.array(likes, pa.float64())], names=["lang", "length", "likeness"])

    rows = labelled.where("lang is not null").select("text", F.col("lang").cast("string").alias("lang")).mapInArrow(run, "lang string, length int, likeness double")
    rows = rows.groupBy("lang", "length", (F.round(F.col("likeness") * STEPS) / STEPS).alias("likeness")).agg(F.count(F.lit(1)).alias("times"))
    cells = rows.cube("lang", "length").agg(F.percentile("likeness", F.lit(LOW), F.col("times")).alias("low"), F.sum("times").alias("n")).where(f"length is not null and n >= {ENOUGH}")
    return {(r.lang, r.length): r.low for r in cells.collect()}


def keep_known(docs: DataFrame, least: float = 0.5, share: float = 0.5) -> DataFrame:
    """The rows of docs with a recognised language: not `und`, a score of `least` or more (0.5: a cosine of 0), and a likeness to the
    language of `share` or more of the low quantile that its training texts of like length have (those of all languages, where it has too few;
    no such cut where all have)."""
    held = F.coalesce(fold(F.col("doc_id"), 4) == 2, F.lit(False))
    training = docs.where(~held).select("text", "lang")
    known = profiles(training)
    classify, low = Classifier(known), low_likeness(training, known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder()

        def good(text: str | None) -> bool:
            v = encoder.encode(text) if known else None
            lang, score = classify.judge(v)
            if lang == "und" or score < least:
                return False
            length = length_class(text)
            cut = low.get((lang, length), low.get((None, length)))
            return cut is None or classify.likeness(v, lang) >= share * cut

        for b in batches:
            yield b.filter(pa.array([good(t.as_py()) for t in b.column("text")], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
