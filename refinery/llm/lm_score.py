"""Language-model scores: a hashed maximum-entropy model with a class-factored softmax.

Tokens are a text's words with A-Z lower-cased, then one end token. The model gives
    P(word | history) = P(class | history) * P(slot | class, history) * P(word | class's rest)
where the commonest words have a slot of their own in one of CLASSES classes (dealt by frequency), and every other word shares the
last slot of the class that its last letters hash to; in there it has its smoothed share of the class's training counts, an
unseen word the share of one unseen type. Classes and slots are softmaxes over features hashed into one table of weights each: the
word before and the pair before (n-grams), and the word two back (a skip). A history is known by its words' slots, so there are at most
(OWN + CLASSES + 1) squared histories.

On top of it are the pairs of words as they stand, of all training texts: with n(v, w) how often w follows v, and n(v) how often v has a
next word, P(w | history, v) = (n(v, w) + PRIOR * model) / (n(v) + PRIOR), where model is the probability above. All pairs count, however rare.

All training texts are counted into histories and what follows them; that table of codes is bounded whatever the corpus's size. Its rows are
shared out to tasks, which send back their gradients round by round; the driver adds them up and moves the weights by
the mean slope of each row. Texts are scored in numpy, a softmax for each distinct history of a slice.

Texts are dealt to slices by a hash of their rows. A slice asks for the counts of its distinct pairs, and of its words beyond the head: sorted keys, each with
the slice's own count, packed and cut by hash into buckets. A bucket adds up what all slices sent and answers each in the order in which it asked, so the answer is
counts alone. No table of pairs is written or joined, no token is a row, and a scored text meets its counts in its slice.

Word counts are a distributed table. Tasks hold a head of it, of at most HEAD words; slices ask for the others, so memory does not grow with the vocabulary.

Defined results: a null or empty text is the end token alone. Texts with a null doc_id train. Without training texts N and V are 0 and every
token's probability is as the smoothing leaves it. Repeated rows are scored (and counted) each.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from refinery.llm.common import drop_stage, mix, release, stage
from refinery.llm.language import fold

#: The base model's smoothing, and the held-out fold.
ADD, FOLDS, HELD = 0.1, 10, 0
END = b""
#: Words whose counts every task holds; classes; slots in a class, the last one for the class's rest.
HEAD, CLASSES, SLOTS = 65_536, 32, 32
OWN = CLASSES * (SLOTS - 1)
#: Codes of a history's words: own slots, rests, and the text's start.
START = OWN + CLASSES
CODES = START + 1
#: Rows of each hashed table of weights, gradient rounds, tasks that share them out (the histories are bounded, so few are enough), step size, and
#: how many sightings halve a row's step.
ROWS, ROUNDS, TASKS, STEP, DAMP = 1 << 15, 10, 4, 1.0, 4.0
#: What the model weighs beside a pair's sightings.
PRIOR = 20.0
#: Tokens in a batch, and weight rows sent together.
BATCH, CHUNK = 200_000, 64
#: Bytes of text in a slice and in what a bucket is asked for, about.
SLICE, BUCKET = 4_000_000, 6_000_000
#: What slices send: cells of both levels, pairs, words beyond the head.
CELLS, PAIR, WORD = (0, 1), 2, 3


def tokens_of(text: str | None) -> list[bytes]:
    """bytes.split() parts at the six ASCII blanks, so its words are the runs without them."""
    found = (text or "").encode("utf-8", "surrogatepass").lower().split()
    found.append(END)
    return found


def rest_class(token: bytes) -> int:
    return zlib.crc32(token[-3:]) % CLASSES


def count_tokens(texts: DataFrame) -> DataFrame:
    """token, c over all rows of texts (text). Tasks count first, in tables of bounded size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: Counter = Counter()

        def flush() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(list(counts), pa.binary()), pa.array(list(counts.values()), pa.int64())], names=["token", "c"])
            counts.clear()
            return out

        for b in batches:
            for text in b.column("text"):
                counts.update(tokens_of(text.as_py()))
                if len(counts) > 300_000:
                    yield flush()
        yield flush()

    return texts.select("text").mapInArrow(run, "token binary, c long").groupBy("token").agg(F.sum("c").alias("c"))


class Vocabulary:
    """What every task knows of the counts; its size is bounded by HEAD and CLASSES."""

    def __init__(self, head: dict[bytes, int], total: int, types: int, rest_counts: np.ndarray, rest_types: np.ndarray):
        self.total, self.types = total, types
        self.words = sorted(head, key=lambda w: (-head[w], w))
        self.counts = np.array([head[w] for w in self.words], dtype=np.float64)
        self.rest = rest_counts + ADD * (rest_types + 1)

    def numbers(self) -> dict[bytes, int]:
        """Each head word's place; other words get len(words) + the class of their rest."""
        return {w: k for k, w in enumerate(self.words)}

    def hashes(self) -> np.ndarray:
        """Of the head words, computed once a task."""
        if not hasattr(self, "_hashes"):
            self._hashes = np.array([word_hash(w) for w in self.words], dtype=np.uint64)
        return self._hashes

    def codes(self) -> np.ndarray:
        """From those numbers to codes of a history."""
        rest = [OWN + rest_class(w) for w in self.words[OWN:]]
        return np.array([*range(min(OWN, len(self.words))), *rest, *range(OWN, OWN + CLASSES)], dtype=np.int64)


def gather_vocabulary(counts: DataFrame) -> Vocabulary:
    """The commonest words by a count that at most HEAD words reach, and sums over the rest, by class."""
    by_count = counts.groupBy("c").agg(F.count(F.lit(1)).alias("n"))
    upto = by_count.withColumn("upto", F.sum("n").over(Window.orderBy(F.col("c").desc()).rowsBetween(Window.unboundedPreceding, 0)))
    least = upto.where(F.col("upto") <= HEAD).agg(F.min("c")).first()[0]
    tied = None if least is not None else by_count.agg(F.max("c")).first()[0]  # more words than HEAD at the top count: some of them, by hash
    total, types = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    if least is not None:
        head = {bytes(r.token): r.c for r in counts.where(F.col("c") >= least).collect()}
    else:
        head = {bytes(r.token): r.c for r in counts.where(F.col("c") == (tied or 0)).orderBy(F.xxhash64("token")).limit(HEAD).collect()}
    klass = F.pmod(F.crc32(F.substring("token", -3, 3)), F.lit(CLASSES))
    klass = F.when(F.length("token") < 3, F.pmod(F.crc32("token"), F.lit(CLASSES))).otherwise(klass)
    n, c = np.zeros(CLASSES), np.zeros(CLASSES)
    for r in counts.groupBy(klass.alias("k")).agg(F.sum("c").alias("c"), F.count(F.lit(1)).alias("n")).collect():
        c[r.k], n[r.k] = r.c, r.n
    voc = Vocabulary(head, int(total), int(types), c, n)
    for w in voc.words[:OWN]:  # words with a slot of their own aren't in the rest
        c[rest_class(w)] -= head[w]
        n[rest_class(w)] -= 1
    return Vocabulary(head, int(total), int(types), c, n)


def numbered(batches: Iterator[pa.RecordBatch], voc: Vocabulary) -> Iterator[tuple[pa.RecordBatch, list[list[bytes]], np.ndarray, np.ndarray]]:
    """Slices of the batches with about BATCH tokens: (rows, tokens of each text, numbers of all tokens, where each text starts).
    A single text may be longer."""
    known, fixed = voc.numbers(), len(voc.words)
    extra = 0
    for b in batches:
        texts, first, held = [], 0, 0
        for k, text in enumerate(b.column("text")):
            texts.append(tokens_of(text.as_py()))
            held += len(texts[-1])
            if held >= BATCH or k == b.num_rows - 1:
                numbers = []
                for found in texts:
                    try:
                        numbers.append(np.fromiter(map(known.__getitem__, found), np.int64, len(found)))
                    except KeyError:
                        if extra > 400_000:
                            known, extra = voc.numbers(), 0
                        for t in found:
                            if t not in known:
                                known[t] = fixed + rest_class(t)
                                extra += 1
                        numbers.append(np.fromiter(map(known.__getitem__, found), np.int64, len(found)))
                starts = np.cumsum([0, *map(len, numbers[:-1])])
                yield b.slice(first, k + 1 - first), texts, np.concatenate(numbers), starts
                texts, first, held = [], k + 1, 0


def word_hash(token: bytes) -> int:
    return xxhash.xxh3_64_intdigest(token)


def pair_keys(head: np.ndarray, texts: list[list[bytes]], numbers: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """A 64-bit key of each token and the one before it (0 at a text's start). head: hashes of the head words; others are hashed here."""
    rare = np.flatnonzero(numbers >= len(head))
    words = np.empty(len(numbers), np.uint64)
    words[numbers < len(head)] = head[numbers[numbers < len(head)]]
    words[rare] = np.array([word_hash(t) for t in tokens_at(texts, rare, starts)], dtype=np.uint64)
    before = np.concatenate((np.zeros(1, np.uint64), words[:-1]))
    before[starts] = 0
    return mix(mix(before, 1) ^ words, 2).view(np.int64)


def tokens_at(texts: list[list[bytes]], where: np.ndarray, starts: np.ndarray) -> list[bytes]:
    """The tokens at these places of a slice, in order."""
    of = np.searchsorted(starts, where, side="right") - 1
    return [texts[t][k] for t, k in zip(of.tolist(), (where - starts[of]).tolist())]


def histories(codes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """(two back) * CODES + (one back) for each token; a text's first tokens have the start before them."""
    one = np.concatenate(([START], codes[:-1]))
    one[starts] = START
    two = np.concatenate(([START], one[:-1]))
    two[starts] = START
    return two * CODES + one


def class_of(codes: np.ndarray) -> np.ndarray:
    return np.where(codes < OWN, codes // (SLOTS - 1), codes - OWN)


def slot_of(codes: np.ndarray) -> np.ndarray:
    return np.where(codes < OWN, codes % (SLOTS - 1), SLOTS - 1)


def hashed(kind: int, value: np.ndarray) -> np.ndarray:
    """A feature's row; row 0 is the bias."""
    h = (value.astype(np.int64) + 1) * (0x9E3779B1 + 2 * kind * 0x61C88647) & 0x7FFFFFFFFFFF
    return 1 + (h ^ (h >> 17)) % (ROWS - 1)


def class_features(history: np.ndarray) -> list[np.ndarray]:
    one, two = history % CODES, history // CODES
    return [np.zeros(len(history), dtype=np.int64), hashed(0, one), hashed(1, history), hashed(2, two)]


def slot_features(place: np.ndarray) -> list[np.ndarray]:
    """place: (one back) * CLASSES + class."""
    return [hashed(3, place % CLASSES), hashed(4, place)]


def log_softmax(weights: np.ndarray, rows: list[np.ndarray]) -> np.ndarray:
    x = weights[rows[0]]
    for r in rows[1:]:
        x = x + weights[r]
    x -= x.max(axis=1, keepdims=True)
    return x - np.log(np.exp(x).sum(axis=1, keepdims=True))


LEVELS = ((class_features, CLASSES), (slot_features, SLOTS))


def pack_bytes(data: bytes) -> bytes:
    return len(data).to_bytes(8, "little") + pa.compress(data, "zstd", asbytes=True)


def unpack_bytes(data: bytes) -> bytes:
    return pa.decompress(data[8:], int.from_bytes(data[:8], "little"), "zstd", asbytes=True)


def pack(values: np.ndarray) -> bytes:
    """Integers as planes of their bytes, so that what is alike stands together."""
    return pack_bytes(values.astype(np.uint64).view(np.uint8).reshape(-1, 8).T.tobytes())


def unpack(data: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(unpack_bytes(data), np.uint8).reshape(8, -1).T).view(np.uint64).ravel()


def pack_sorted(keys: np.ndarray) -> bytes:
    """By their steps, which have fewer bits than the keys."""
    return pack(np.diff(keys, prepend=np.uint64(0)))


def unpack_sorted(data: bytes) -> np.ndarray:
    return np.cumsum(unpack(data), dtype=np.uint64)


def tokens_of_slice(rows: pa.Table, voc: Vocabulary) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """Of all texts of a slice: the tokens' numbers, where each text starts, the tokens' pair keys, and the tokens beyond the head in order."""
    numbers, starts, keys, rare, at = [], [], [], [], 0
    for _, texts, found, begin in numbered(rows.to_batches(), voc):
        numbers.append(found)
        starts.append(begin + at)
        keys.append(pair_keys(voc.hashes(), texts, found, begin).view(np.uint64))
        rare += tokens_at(texts, np.flatnonzero(found >= len(voc.words)), begin)
        at += len(found)
    return np.concatenate(numbers), np.concatenate(starts), np.concatenate(keys), rare


def bucket_bounds(keys: np.ndarray, bits: int) -> np.ndarray:
    """Where each bucket starts in sorted keys, which are hashes: buckets are by their first bits. One more place at the end."""
    first = np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)
    return np.r_[0, np.searchsorted(keys, first), len(keys)]


def rare_buckets(rare: list[bytes], bits: int) -> dict[int, list[bytes]]:
    """The distinct tokens by bucket, in order."""
    out: dict[int, list[bytes]] = {}
    for t in sorted(set(rare)):
        out.setdefault(word_hash(t) >> 64 - bits, []).append(t)
    return out


ASKED = "kind int, bucket int, slice long, keys binary, counts binary"
ANSWERED = "kind int, slice long, bucket int, keys binary, counts binary"


def ask(voc: Vocabulary, bits: int):
    """What a slice sends of its rows (slice, held, text): kind, bucket, slice, keys, counts. Counts are those of its training texts."""

    def run(rows: pa.Table) -> pa.Table:
        numbers, starts, keys, rare = tokens_of_slice(rows, voc)
        trains = np.repeat(~rows.column("held").to_numpy(), np.diff(np.r_[starts, len(numbers)]))
        codes, number, out = voc.codes()[numbers], rows.column("slice")[0].as_py(), []
        past = histories(codes, starts)[trains]
        klass, slot = class_of(codes[trains]), slot_of(codes[trains])
        for kind, cells in zip(CELLS, (past * CLASSES + klass, (past % CODES * CLASSES + klass) * SLOTS + slot)):
            cells, n = np.unique(cells, return_counts=True)
            of = (mix((cells // SLOTS).astype(np.uint64), 3) >> np.uint64(64 - bits)).astype(np.int64)
            for k in np.unique(of).tolist():
                out.append((kind, k, number, pack_sorted(cells[of == k].astype(np.uint64)), pack(n[of == k])))
        keys, inverse = np.unique(keys, return_inverse=True)
        n, ends = np.bincount(inverse, trains, len(keys)), bucket_bounds(keys, bits)
        for k in np.flatnonzero(np.diff(ends)).tolist():
            part = slice(ends[k], ends[k + 1])
            out.append((PAIR, k, number, pack_sorted(keys[part]), pack(n[part])))
        met = Counter(t for t, here in zip(rare, trains[numbers >= len(voc.words)].tolist()) if here)
        for k, tokens in rare_buckets(rare, bits).items():
            out.append((WORD, k, number, pack_bytes(b"\n".join(tokens)), pack(np.array([met[t] for t in tokens]))))  # no token holds a line's end
        types = (pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary())
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names=["kind", "bucket", "slice", "keys", "counts"])

    return run


def answer(rows: pa.Table) -> pa.Table:
    """What a bucket adds up: for cells one row of keys and counts; for pairs and words a row a slice, the counts in the order of its keys."""
    kind, bucket = rows.column("kind")[0].as_py(), rows.column("bucket")[0].as_py()
    sent, own = rows.column("keys").to_pylist(), [unpack(c) for c in rows.column("counts").to_pylist()]
    slices, none = rows.column("slice").to_pylist(), [None] * rows.num_rows
    if kind == WORD:
        total: Counter = Counter()
        asked = [unpack_bytes(k).split(b"\n") for k in sent]
        for tokens, n in zip(asked, own):
            for t, c in zip(tokens, n.tolist()):
                total[t] += c
        counts = [pack(np.array([total[t] for t in tokens])) for tokens in asked]
    else:
        asked = [unpack_sorted(k) for k in sent]
        keys, inverse = np.unique(np.concatenate(asked), return_inverse=True)
        sums = np.bincount(inverse, np.concatenate(own))
        if kind in CELLS:
            slices, none, counts = [None], [pack_sorted(keys)], [pack(sums)]
        else:
            counts = [pack(part) for part in np.split(sums[inverse], np.cumsum([len(a) for a in asked[:-1]]))]
    columns = ([kind] * len(counts), slices, [bucket] * len(counts), none, counts)
    types = (pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary())
    return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], names=["kind", "slice", "bucket", "keys", "counts"])


def cells_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """level, place, counts: for level 0, a history and how often each class follows; for level 1, a word before and a class, and how often each slot."""
    for b in batches:
        for kind, keys, counts in zip(b.column("kind").to_pylist(), b.column("keys").to_pylist(), b.column("counts").to_pylist()):
            keys = unpack_sorted(keys).astype(np.int64)
            places, at = np.unique(keys // SLOTS, return_inverse=True)
            held = np.zeros((len(places), SLOTS))
            held[at, keys % SLOTS] = unpack(counts)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(places) + 1) * SLOTS, pa.int32()), pa.array(held.ravel()))
            for k in range(0, len(places), 10_000):
                part = lists.slice(k, 10_000)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), kind, np.int32)), pa.array(places[k : k + 10_000]), part], names=["level", "place", "counts"])


def train(table: DataFrame, rounds: int = ROUNDS) -> list[np.ndarray]:
    """Fit both levels' weights to the counted histories (a table in the shared folder, read in each round)."""
    weights = [np.zeros((ROWS, n), np.float32) for _, n in LEVELS]
    for _ in range(rounds):
        now = table.sparkSession.sparkContext.broadcast(weights)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            slopes = [np.zeros((ROWS, n)) for _, n in LEVELS]
            met = [np.zeros(ROWS) for _ in LEVELS]
            for b in batches:
                level = b.column("level").to_numpy()
                place, counts = b.column("place").to_numpy(), b.column("counts").flatten().to_numpy().reshape(b.num_rows, -1)
                for k, (of, n) in enumerate(LEVELS):
                    some = level == k
                    if some.any():
                        rows, c = of(place[some]), counts[some][:, :n]
                        total = c.sum(axis=1)
                        slope = total[:, None] * np.exp(log_softmax(now.value[k], rows)) - c
                        for r in rows:
                            order = np.argsort(r, kind="stable")
                            first = np.flatnonzero(np.r_[True, np.diff(r[order]) != 0])
                            at = r[order][first]
                            slopes[k][at] += np.add.reduceat(slope[order], first, axis=0)
                            met[k][at] += np.add.reduceat(total[order], first)
            task, out = TaskContext.get().partitionId(), []
            for k in range(len(LEVELS)):
                for at in range(0, ROWS, CHUNK):
                    if met[k][at : at + CHUNK].any():
                        out.append((k * ROWS + at, task, slopes[k][at : at + CHUNK].astype(np.float32).tobytes(), met[k][at : at + CHUNK].tobytes()))
            columns = list(zip(*out)) or [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int32(), pa.int32(), pa.binary(), pa.binary()))], names=["chunk", "task", "slope", "met"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            chunk, slope, met = None, None, None
            row = lambda: pa.RecordBatch.from_arrays([pa.array([chunk], pa.int32()), pa.array([(slope / (met + DAMP)[:, None]).astype(np.float32).tobytes()], pa.binary())], names=["chunk", "change"])
            for b in batches:
                for c, g, m in zip(b.column("chunk").to_pylist(), b.column("slope").to_pylist(), b.column("met").to_pylist()):
                    m = np.frombuffer(m, np.float64)
                    g = np.frombuffer(g, np.float32).astype(np.float64).reshape(len(m), -1)
                    if c != chunk:
                        if chunk is not None:
                            yield row()
                        chunk, slope, met = c, g, m
                    else:
                        slope, met = slope + g, met + m
            if chunk is not None:
                yield row()

        sent = table.coalesce(TASKS).mapInArrow(run, "chunk int, task int, slope binary, met binary")
        summed = sent.repartition("chunk").sortWithinPartitions("chunk", "task").mapInArrow(add, "chunk int, change binary")
        weights = [w.copy() for w in weights]
        for r in summed.collect():  # at most the weights' own size
            w, at = weights[r.chunk // ROWS], r.chunk % ROWS
            w[at : at + CHUNK] -= STEP * np.frombuffer(r.change, np.float32).reshape(CHUNK, -1)
        now.destroy()  # else the weights of all rounds stay on every disk
    return weights


def score(sliced: DataFrame, answers: DataFrame, voc: Vocabulary, weights: list[np.ndarray], n_texts: int, bits: int) -> DataFrame:
    """doc_id, held, n_tokens, n_known, base_score, score for every row of sliced (slice, doc_id, held, text), with the answers to its slice."""
    log_all, slots = float(np.log10(voc.total + ADD * (voc.types + 1))), []

    def run(rows: pa.Table, met: pa.Table) -> pa.Table:
        numbers, starts, keys, rare = tokens_of_slice(rows, voc)
        if not slots:  # once a task
            slots.append(log_softmax(weights[1], slot_features(np.arange(CODES * CLASSES))) / np.log(10))
        told = dict(zip(zip(met.column("kind").to_pylist(), met.column("bucket").to_pylist()), met.column("counts").to_pylist()))
        distinct, inverse = np.unique(keys, return_inverse=True)
        pairs = np.concatenate([unpack(told[PAIR, k]) for k in np.flatnonzero(np.diff(bucket_bounds(distinct, bits))).tolist()])[inverse].astype(np.float64)
        seen = {t: c for k, tokens in rare_buckets(rare, bits).items() for t, c in zip(tokens, unpack(told[WORD, k]).tolist())}
        # the counts of all tokens: of the head, or as answered
        is_rare = numbers >= len(voc.words)
        c = np.concatenate((voc.counts, np.zeros(CLASSES)))[numbers]
        c[is_rare] = [seen[t] for t in rare]
        log_c, to_code = np.log10(c + ADD), voc.codes()
        codes = to_code[numbers]
        places, inverse = np.unique(histories(codes, starts), return_inverse=True)
        klass, one = class_of(codes), places[inverse] % CODES
        model = np.empty(len(codes))
        for at in range(0, len(places), 50_000):  # bounds the softmaxes' memory
            some = (inverse >= at) & (inverse < at + 50_000)
            model[some] = (log_softmax(weights[0], class_features(places[at : at + 50_000])) / np.log(10))[inverse[some] - at, klass[some]]
        # a word with a slot of its own needs no share of a rest
        model += slots[0][one * CLASSES + klass, slot_of(codes)] + np.where(codes < OWN, 0.0, log_c - np.log10(voc.rest)[np.maximum(codes - OWN, 0)])
        before = np.log10(np.concatenate(([0.0], c[:-1])) + PRIOR)
        before[starts] = np.log10(n_texts + PRIOR)
        logs = np.log10(pairs + PRIOR * 10.0**model) - before
        lengths = np.diff(np.r_[starts, len(numbers)]).astype(np.int64)
        known, base, total = (np.add.reduceat(x, starts) for x in ((c > 0).astype(np.int64), log_c, logs))
        arrays = [rows.column("doc_id"), rows.column("held"), pa.array(lengths), pa.array(known), pa.array(base - lengths * log_all), pa.array(total)]
        return pa.Table.from_arrays(arrays, names=["doc_id", "held", "n_tokens", "n_known", "base_score", "score"])

    schema = "doc_id long, held boolean, n_tokens long, n_known long, base_score double, score double"
    return sliced.groupBy("slice").cogroup(answers.select("slice", "kind", "bucket", "counts").groupBy("slice")).applyInArrow(run, schema)


def lm_scores(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score; learned from the rows that aren't held out."""
    held = F.coalesce(fold(F.col("doc_id"), FOLDS) == HELD, F.lit(False))
    counts = stage(count_tokens(docs.where(~held).select("text")), "counts")
    release(docs.sparkSession)
    voc = gather_vocabulary(counts)
    n_texts = counts.where(F.length("token") == 0).agg(F.coalesce(F.sum("c"), F.lit(0))).first()[0]
    drop_stage(counts)
    size = docs.agg(F.coalesce(F.sum(F.octet_length(F.coalesce("text", F.lit(""))) + 8), F.lit(0))).first()[0]
    bits = max(4, (size // BUCKET).bit_length())
    # of equal rows, any order is the same; others are told apart by the hash, whatever is recomputed later
    part = F.pmod(F.xxhash64("doc_id", "text"), F.lit(size // SLICE + 1))
    sliced = docs.select(part.alias("slice"), F.col("doc_id").cast("long").alias("doc_id"), held.alias("held"), "text")
    asked = sliced.select("slice", "held", "text").groupBy("slice").applyInArrow(ask(voc, bits), ASKED)
    answers = stage(asked.groupBy("kind", "bucket").applyInArrow(answer, ANSWERED), "answers")
    release(docs.sparkSession)
    cells = stage(answers.where(F.col("kind").isin(*CELLS)).select("kind", "keys", "counts").mapInArrow(cells_of, "level int, place long, counts array<double>"), "histories")
    weights = train(cells)
    drop_stage(cells)
    release(docs.sparkSession)
    rows = score(sliced, answers.where(~F.col("kind").isin(*CELLS)), voc, weights, n_texts, bits)
    return rows.select("doc_id", F.col("held").alias("held_out"), "n_tokens", "n_known", F.lit(voc.total).cast("long").alias("train_tokens"), "base_score", "score")
