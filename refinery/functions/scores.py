"""Scores of texts against texts, in Python over Arrow batches: sets and bit vectors in place of arrays that the JVM copies for each word. The same numbers
as their column forms, which tests hold them against; blanks, digits and sentences are what the column functions take them for."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable
from functools import reduce
from itertools import chain
from operator import add

import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

_NUMBER = re.compile("[0-9]+")


def words_of(text: str) -> list[bytes]:
    """bytes.split() parts at the six ASCII blanks, as the column function does."""
    return text.encode("utf-8", "surrogatepass").split()


def _evidence(source: str, n: int) -> tuple[set, set, set]:
    w = words_of(source)
    return set(w), set(zip(*(w[k:] for k in range(n)))), set(_NUMBER.findall(source))


def _support(claim: str, denies: bool, known_words: set, grams: set, numbers: set, n: int) -> float:
    w = words_of(claim)
    own = set(w)
    known = len(own & known_words) / max(len(own), 1)
    share = known
    if len(own) >= n:
        mine = set(zip(*(w[k:] for k in range(n))))
        share = len(mine & grams) / len(mine)
    accuracy = 1.0 if numbers.issuperset(_NUMBER.findall(claim)) else 0.3
    return min(accuracy, share, 0.3 if denies else 1.0, known)


def mean_support(n: int):
    """claims (lower-cased, a line each), a mark for each claim (1: denies), source (lower-cased), whether the source denies; the mean support, 0 without claims."""

    @F.arrow_udf(DoubleType())
    def score(claims: pa.Array, marks: pa.Array, sources: pa.Array, denying: pa.Array) -> pa.Array:
        out, last, held = [], None, None
        for text, mark, source, denied in zip(claims.to_pylist(), marks.to_pylist(), sources.to_pylist(), denying.to_pylist()):
            if not text:
                out.append(0.0)
                continue
            if source != last:  # questions on a passage follow one another
                last, held = source, _evidence(source, n)
            found = text.split("\n")
            total = 0.0
            for claim, m in zip(found, mark):
                total += _support(claim, m == "1" and not denied, *held, n)
            out.append(total / len(found))
        return pa.array(out, pa.float64())

    return score


def mean_supports(n: int):
    """mean_support of several texts against one source, whose evidence is taken once: arrays of claims (null: no text) and of marks; an array of means."""

    @F.arrow_udf(ArrayType(DoubleType()))
    def score(claims: pa.Array, marks: pa.Array, sources: pa.Array, denying: pa.Array) -> pa.Array:
        out, last, held = [], None, None
        for texts, marked, source, denied in zip(claims.to_pylist(), marks.to_pylist(), sources.to_pylist(), denying.to_pylist()):
            if source != last:
                last, held = source, _evidence(source, n)
            row = []
            for text, mark in zip(texts, marked):
                found, total = text.split("\n") if text else [], 0.0
                for claim, m in zip(found, mark or ""):
                    total += _support(claim, m == "1" and not denied, *held, n)
                row.append(total / len(found) if found else 0.0)
            out.append(row)
        return pa.array(out, pa.list_(pa.float64()))

    return score


def common_subsequence(a: list, b: list) -> int:
    """Length of the longest common subsequence: a bit for each place of b, a step for each word of a."""
    places: dict = {}
    for k, w in enumerate(b):
        places[w] = places.get(w, 0) | 1 << k
    full = (1 << len(b)) - 1
    row = full
    for w in a:
        if hit := row & places.get(w, 0):
            row = (row + hit | row - hit) & full
    return len(b) - row.bit_count()


def plain_sum(values: Iterable[float]) -> float:
    """In order and without the compensation of sum(), as the JVM adds up."""
    return reduce(add, values, 0.0)


@F.arrow_udf(DoubleType())
def rouge_l(hyps: pa.Array, refs: pa.Array) -> pa.Array:
    """Of lower-cased texts."""
    out = []
    for hyp, ref in zip(hyps.to_pylist(), refs.to_pylist()):
        h, r = words_of(hyp), words_of(ref)
        found = common_subsequence(h, r)
        out.append(2.0 * found / (len(h) + len(r)) if found else 0.0)
    return pa.array(out, pa.float64())


@F.arrow_udf(DoubleType())
def match_f1(hyps: pa.Array, refs: pa.Array) -> pa.Array:
    """Of lower-cased texts."""
    bigrams: dict[bytes, frozenset] = {}

    def grams(w: bytes) -> frozenset:
        if (found := bigrams.get(w)) is None:
            t = w.decode("utf-8", "surrogatepass")
            found = bigrams[w] = frozenset(t[k : k + 2] for k in range(max(len(t) - 1, 1)))
        return found

    def both(h: list, r: list) -> tuple[float, float]:
        """Each side's mean of its words' best matches; only words that share a bigram are compared."""
        if not h or not r:
            return 0.0, 0.0
        best_h, best_r, having = dict.fromkeys(h, 0.0), dict.fromkeys(r, 0.0), {}
        for y in best_r:
            for g in grams(y):
                having.setdefault(g, []).append(y)
        for x in best_h:
            mine = grams(x)
            shared = Counter(chain.from_iterable(having.get(g, ()) for g in mine))
            for y, n in shared.items():
                alike = 2.0 * n / (len(mine) + len(grams(y)))
                if alike > best_h[x]:
                    best_h[x] = alike
                if alike > best_r[y]:
                    best_r[y] = alike
        return plain_sum(map(best_h.__getitem__, h)) / len(h), plain_sum(map(best_r.__getitem__, r)) / len(r)

    out = []
    for hyp, ref in zip(hyps.to_pylist(), refs.to_pylist()):
        if len(bigrams) > 200_000:  # bounds the memory
            bigrams.clear()
        h, r = words_of(hyp), words_of(ref)
        p, q = both(h, r)
        out.append(2 * p * q / (p + q) if p + q > 0 else 0.0)
    return pa.array(out, pa.float64())
