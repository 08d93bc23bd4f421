"""Edit-aware token counts.

Text is cut where a character that isn't white space is followed by one that is: no pre-token of the byte-level BPE pattern
spans such a place, and no pre-token depends on what lies beyond it, so a text's count is the sum of its pieces'
counts. Long pieces are cut further where an ASCII letter, digit or sign is followed by one of another of these kinds, but for an
apostrophe before (it may begin a contraction): pre-tokens end there as well. A document keeps its pieces in leaves, and a segment
tree over the leaves holds (characters, tokens). An edit finds its leaves by descending on characters, widens to the leaves of
the characters next to it (the boundary context: an edit may join two pieces or part one), re-encodes only those, and updates the sums
above them. A leaf that outgrows its bound is split; the other leaves keep their counts, and only sums are added anew.

Runs in mapInArrow, a document at a time; memory is bounded by the longest text, a vocabulary and a bounded memory of
piece counts. A pre-token longer than a leaf (letters or white space without end) is one piece, since BPE merges run through all of it.
Defined results: null and empty texts have 0 tokens; edits beyond the end are clipped; a null edit list edits nothing.
Special tokens' strings count as ordinary text. `vocabulary` is a path on every executor; a missing file is an error that names it.
"""

from __future__ import annotations

import base64
import os
import re
from collections.abc import Iterator

import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame

#: The pre-token pattern of the byte-level BPE vocabularies, and the white space it knows (Unicode White_Space).
PATTERN = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
WHITE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
PIECE = re.compile(f"[{WHITE}]*[^{WHITE}]+|[{WHITE}]+")
VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: In a long piece, where ASCII letters, digits and signs meet.
MEET = re.compile(r"(?<=[A-Za-z])(?=[0-9])|(?<=[0-9])(?=[A-Za-z])|(?<=[A-Za-z0-9])(?=[!-/:-@\[-`{-~])|(?<=[!-&(-/:-@\[-`{-~])(?=[A-Za-z0-9])")
#: Pieces and characters in a new leaf, characters at which a leaf is split, length of a long piece, piece counts remembered.
LEAF, LEAF_CHARS, FULL, LONG, REMEMBERED = 64, 2_048, 8_192, 256, 400_000


def pieces_of(text: str) -> list[str]:
    found = PIECE.findall(text)
    if max(map(len, found), default=0) <= LONG:
        return found
    return [x for p in found for x in (MEET.split(p) if len(p) > LONG else (p,))]


class Counter:
    """Token counts of texts, piece by piece, with bounded memory."""

    def __init__(self, vocabulary: str = VOCABULARY):
        if not os.path.exists(vocabulary):
            raise FileNotFoundError(f"no vocabulary at {vocabulary!r} on this executor; pass vocabulary= or ship the file to it")
        with open(vocabulary, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.encoding = tiktoken.Encoding("counts", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.known: dict[str, int] = {}
        #: Characters of the pieces asked for, and of those not remembered, which were encoded.
        self.given = self.encoded = 0

    def pieces(self, pieces: list[str]) -> int:
        known = self.known
        self.given += sum(map(len, pieces))
        try:
            return sum(map(known.__getitem__, pieces))
        except KeyError:
            pass
        if len(known) > REMEMBERED:
            known.clear()
        for p in pieces:
            if p not in known:
                known[p] = len(self.encoding.encode_ordinary(p))
                self.encoded += len(p)
        return sum(map(known.__getitem__, pieces))

    def text(self, text: str) -> int:
        return self.pieces(pieces_of(text))


def leaves_of(text: str) -> list[list[str]]:
    """The pieces of a text in groups of LEAF, or of LEAF_CHARS characters."""
    out, held = [[]], 0
    for p in pieces_of(text):
        if len(out[-1]) >= LEAF or held and held + len(p) > LEAF_CHARS:
            out.append([])
            held = 0
        out[-1].append(p)
        held += len(p)
    return out


class SegmentTree:
    """A document's leaves of pieces, and sums of characters and tokens over them."""

    def __init__(self, text: str, counter: Counter):
        self.counter, self.reencoded = counter, 0
        groups = leaves_of(text)
        self._deal([("".join(g), counter.pieces(g)) for g in groups])

    def _deal(self, leaves: list[tuple[str, int]]) -> None:
        """The tree over leaves and their tokens, which are counted already."""
        self.leaves = [t for t, _ in leaves]
        self.width = 1
        while self.width < len(leaves):
            self.width *= 2
        self.chars, self.tokens = [0] * (2 * self.width), [0] * (2 * self.width)
        for k, (text, n) in enumerate(leaves):
            self.chars[self.width + k], self.tokens[self.width + k] = len(text), n
        for k in range(self.width - 1, 0, -1):
            self._add(k)

    def _add(self, k: int) -> None:
        self.chars[k] = self.chars[2 * k] + self.chars[2 * k + 1]
        self.tokens[k] = self.tokens[2 * k] + self.tokens[2 * k + 1]

    @property
    def n_chars(self) -> int:
        return self.chars[1]

    @property
    def n_tokens(self) -> int:
        return self.tokens[1]

    def text(self) -> str:
        return "".join(self.leaves)

    def find(self, at: int) -> tuple[int, int]:
        """The leaf of the character at a place, and the place in it."""
        k = 1
        while k < self.width:
            k *= 2
            if at >= self.chars[k] and self.chars[k + 1]:
                at -= self.chars[k]
                k += 1
        return k - self.width, at

    def edit(self, start: int, end: int, new: str) -> None:
        """Replace characters start to end by `new`; re-encodes the leaves touched and those next to a cut."""
        start = max(0, min(start, self.n_chars))
        end = max(start, min(end, self.n_chars))
        if not self.n_chars:
            self.reencoded += len(new)
            self._deal([("".join(g), self.counter.pieces(g)) for g in leaves_of(new)])
            return
        first, at = self.find(max(0, start - 1))
        at += start - max(0, start - 1)
        last, to = self.find(min(end, self.n_chars - 1))
        to += end - min(end, self.n_chars - 1)
        changed = self.leaves[first][:at] + new + self.leaves[last][to:]
        self.reencoded += len(changed)
        if len(changed) > FULL:
            fresh = [("".join(g), self.counter.pieces(g)) for g in leaves_of(changed)]
            own = list(zip(self.leaves, self.tokens[self.width :]))
            self._deal([x for x in own[:first] + fresh + own[last + 1 :] if x[0]])
            return
        self.leaves[first] = changed
        for k in range(first + 1, last + 1):
            self.leaves[k] = ""
        touched = set()
        for k in range(first, last + 1):
            node = self.width + k
            self.chars[node], self.tokens[node] = len(self.leaves[k]), self.counter.text(self.leaves[k]) if k == first else 0
            touched.add(node // 2)
        while touched and (up := touched) != {0}:
            for node in sorted(up, reverse=True):
                if node:
                    self._add(node)
            touched = {node // 2 for node in up if node}


#: Spans that the production edits put out: keys, mail and network addresses, phone and card numbers.
SPANS = re.compile(r"token = \"[0-9a-f]{40}\"|[\w.+-]+@[\w-]+(?:\.[\w-]+)+|\b\d{1,3}(?:\.\d{1,3}){3}\b|\+\d{1,2} \(\d{3}\) \d{3}-\d{4}|\b\d{16}\b")
DIGIT_OR_AT = re.compile(r"[0-9@]")
REDACTED = "<redacted>"


def production_edits(text: str) -> list[tuple[int, int, str]]:
    """Edits against the text as it is when each is applied (last place first): redactions, doubled lines out, one line on top."""
    # every span holds a digit or an at sign
    found = [(m.start(), m.end(), REDACTED) for m in SPANS.finditer(text)] if DIGIT_OR_AT.search(text) else []
    seen, at = set(), 0
    for line in text.split("\n"):
        if line.strip() and line in seen and not any(s < at + len(line) and at < e for s, e, _ in found):
            found.append((at - 1, at + len(line), ""))
        seen.add(line)
        at += len(line) + 1
    return [*sorted(found, reverse=True), (0, 0, "document:\n")]


def counts_after_edits(docs: DataFrame, edits=production_edits, vocabulary: str = VOCABULARY) -> DataFrame:
    """doc_id, n_chars, n_tokens, n_edits, n_chars_after, n_tokens_after, n_reencoded (characters) for every row of docs.

    edits: a function from a text to (start, end, new) triples, applied in turn."""
    names = ["n_chars", "n_tokens", "n_edits", "n_chars_after", "n_tokens_after", "n_reencoded"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = Counter(vocabulary)
        for b in batches:
            rows = []
            for text in b.column("text"):
                text = text.as_py() or ""
                tree, todo = SegmentTree(text, counter), edits(text) or []
                before = tree.n_tokens
                for edit in todo:
                    tree.edit(*edit)
                rows.append((len(text), before, len(todo), tree.n_chars, tree.n_tokens, tree.reencoded))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, pa.int64()) for c in list(zip(*rows)) or [()] * 6)], names=["doc_id", *names])

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text"))
    return rows.mapInArrow(run, "doc_id long, " + ", ".join(f"{n} long" for n in names))
