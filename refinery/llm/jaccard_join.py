"""N-gram Jaccard join along chosen paths.

Exact copies first: texts with the same words form one class, so that copies are never compared. Then, for each of
several runs, every set draws the tokens (hashed shingles) whose run hash lies below 1 / (t * size): on average 1 / t of
them, shared tokens being drawn by both sets at once. Sets that drew the same token meet in a bucket. A bucket of at
most `LIMIT` sets is compared by brute force. A larger one is dealt at random into blocks, a few leaders of the bucket join each
block, blocks are compared by brute force, and buckets that are then still in several classes draw again, one step down the path.
Runs repeat until a pair at the threshold is missed with a probability under `1 - recall`.

Classes and output grow in proportion to a group, not with its square: a bucket gives a tree of verified links at most, never all pairs. Where the number of all
links is asked for (`every`), the pairs of each class are compared once more, at the end; they are counted, never listed.
Comparison has two steps: sketches (one-permutation minhash, a margin below the threshold) tell which sets of a block may have a
partner there, then the whole token sets of those decide, where they are more than CROWD in parts that share leaders. The first runs are decided before the others, and a bucket whose
sets are all in one class by then has nothing left to tell, so a large group of near copies is compared in the first runs only.
Leaders leave a split bucket: they have met all of it. What still fills a bucket after the last step down (far texts that share
most of a template) is compared in all pairs of blocks, so no pair that met is left out.

Shuffles: drawn tokens (about fifteen rows a text, 24 bytes), sketches of sets that met, the token sets of candidates; never texts. A scan
for candidates passes rows by a Bloom filter of fixed size first and joins exactly after. Sides of joins grow with the data, so
they are merged at every size; hot keys stand on sides that the adaptive planner can split. Lineage is cut by tables in the shared folder.

Recall: a pair at the threshold shares at least one expected draw a run, and FURTHER below a split. The number of runs is set
for pairs whose buckets are split once (1e-3 missed with 12 runs, 6e-6 without a split, 1e-2 at two splits, if no leader and no third
text links them).

Defined results: a text without words (null, empty, blanks) has no set: its class is its own id, 0 links. A text of fewer than five
words is one shingle. Rows with equal words are copies of one text. doc_id may repeat or be null; a class takes its least
non-null id. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from refinery.llm.common import MIN_SIMILARITY, SHINGLE_WORDS, WordHashes, byte_words, drop_stage, mix, release, shingle_set, stage
from refinery.llm.graph import components, merge_labels

#: Largest bucket whose sketches are compared by brute force; sets in a block of a larger one; bins of a sketch; steps down a path.
LIMIT, BLOCK, BINS, DEPTH = 8192, 4096, 128, 4
#: Most sets that are compared whole in one block; sets in a part of a more crowded one.
CROWD, PART = 1024, 512
#: Largest class whose links are counted in one task; half of it is a part of a larger one.
WHOLE = 2048
#: Leaders of a large bucket; runs that are decided before the others; draws below a split, as a multiple of those above.
LEADERS, EARLY, FURTHER = 4, 2, 1.25
#: Bits of the filter of candidates (8 MB); words that are shingled at once, unless one text has more.
FILTER_BITS, CHUNK = 1 << 26, 300_000
FULL = np.uint64(0xFFFFFFFFFFFFFFFF)


def runs_for(recall: float) -> int:
    """Runs so that a pair at the threshold meets at least once with probability `recall`, one split included: it shares one
    expected draw a run at least (the lesser set inside the greater: t * size tokens at 1 / (t * size)), and FURTHER below the split."""
    meets = (1 - math.exp(-1)) * (1 - math.exp(-FURTHER))
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - meets)))


def draws(tokens: np.ndarray, path: int, below: np.ndarray | np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """Places and keys of the tokens that sets draw below a path; `below` is `drawn_below` of each token's set. Tokens are mixed
    hashes already, so a multiplication and a sum by the path's own numbers give the path's hash."""
    odd, add = (int(x) for x in mix(np.array([path & 0xFFFFFFFFFFFFFFFF, ~path & 0xFFFFFFFFFFFFFFFF], dtype=np.uint64), 3))
    with np.errstate(over="ignore"):
        h = tokens * np.uint64(odd | 1) + np.uint64(add)
    at = np.flatnonzero(h < below)
    return at, mix(tokens[at], (path + 77) & 0xFFFFFFFFFFFF)


def drawn_below(size: int, threshold: float, rate: float = 1.0) -> int:
    """A set of this size draws tokens whose hash is less."""
    return min(2**64 - 1, int(2**64 * rate / (threshold * size))) if size else 0


def sketches_of(tokens: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """A row for each of n sets: 16 bits of the least hash in each bin; 0 marks an empty bin."""
    h = mix(tokens, 5)
    least = np.full(n * BINS, FULL, dtype=np.uint64)
    np.minimum.at(least, owner * BINS + (h >> np.uint64(64 - int(math.log2(BINS)))).astype(np.int64), h)
    bits = (mix(least, 9) & np.uint64(0xFFFF)).astype(np.uint16) | np.uint16(1)
    return np.where(least == FULL, np.uint16(0), bits).reshape(n, BINS)


def relatives(sketches: np.ndarray, threshold: float) -> np.ndarray:
    """The group of each set of the block: sets are joined whose estimated similarity is a margin of 4.5 deviations below the threshold at least; -1 for a
    set without such a partner. No similar pair is in two groups, but for the margin."""
    n = len(sketches)
    group, filled, paired = np.arange(n), sketches != 0, np.zeros(n, dtype=bool)
    for x in range(n - 1):
        rest, one = sketches[x + 1 :], sketches[x]
        either = np.maximum((filled[x] | filled[x + 1 :]).sum(axis=1), 1)
        about = ((one == rest) & filled[x]).sum(axis=1) / either
        near = np.flatnonzero(about >= threshold - 4.5 * np.sqrt(0.2 * 0.8 / either)) + x + 1
        if len(near):
            paired[x] = paired[near] = True
            joined = np.unique(group[near[group[near] != group[x]]])
            if len(joined):
                group[np.isin(group, joined)] = group[x]
    return np.where(paired, group, -1)


def shingle_sets(texts: list[list[bytes]], hashes: WordHashes, width: int) -> list[np.ndarray]:
    """`shingle_set` of each text, hashed together."""
    h = hashes([w for t in texts for w in t])
    n = max(0, len(h) - width + 1)
    windows = np.zeros(n, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(width):
            windows = windows * np.uint64(0x100000001B3) + mix(h[k : n + k], k)
    windows, sets, start = mix(windows), [], 0
    for end in np.cumsum([len(t) for t in texts]).tolist():
        if end - start < width:
            sets.append(shingle_set(h[start:end], width))
        else:
            own = windows[start : end - width + 1]
            own.sort()
            fresh = np.ones(len(own), dtype=bool)
            np.not_equal(own[1:], own[:-1], out=fresh[1:])
            sets.append(own[fresh])
        start = end
    return sets


def _sets(batch: pa.RecordBatch, hashes: WordHashes, width: int) -> Iterator[tuple[list, list[bytes | None], list[np.ndarray]]]:
    """doc_id, uid (16 bytes for a text's words; null without words) and token set of each row, some rows at a time."""
    ids, words, held = [], [], 0
    for i, text in zip(batch.column("doc_id").to_pylist(), batch.column("text")):
        ids.append(i)
        words.append(byte_words(text.as_py()))
        held += len(words[-1])
        if held >= CHUNK:
            yield ids, [hashlib.md5(b" ".join(w)).digest() if w else None for w in words], shingle_sets(words, hashes, width)
            ids, words, held = [], [], 0
    yield ids, [hashlib.md5(b" ".join(w)).digest() if w else None for w in words], shingle_sets(words, hashes, width)


def _groups(batches: Iterator[pa.RecordBatch], key: list[str], others: list[str]) -> Iterator[tuple[tuple, list[list]]]:
    """Runs of equal keys in a sorted partition, across batches."""
    now, held = None, [[] for _ in others]
    for b in batches:
        keys = list(zip(*(b.column(k).to_pylist() for k in key)))
        values = [b.column(o).to_pylist() for o in others]
        at = 0
        while at < len(keys):
            end = at + 1
            while end < len(keys) and keys[end] == keys[at]:
                end += 1
            if keys[at] != now:
                if now is not None:
                    yield now, held
                now, held = keys[at], [[] for _ in others]
            for h, v in zip(held, values):
                h += v[at:end]
            at = end
    if now is not None:
        yield now, held


def overlaps(sets: list[np.ndarray], first: int | None = None) -> np.ndarray:
    """Sizes of the intersections of all pairs of sets, by products of incidence columns, a strip of tokens at a time. `first`: of the first sets, so many,
    with the others only."""
    n = len(sets)
    rows, columns = (slice(None), slice(None)) if first is None else (slice(first), slice(first, None))
    total = np.zeros((n, n) if first is None else (first, n - first), dtype=np.float32)
    _, token, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    shared = times[token] > 1
    column = np.cumsum(times > 1) - 1
    token, owner = column[token[shared]], owner[shared]
    order = np.argsort(token, kind="stable")
    token, owner = token[order], owner[order]
    for at in range(0, int(token[-1]) + 1 if len(token) else 0, 2048):
        lo, hi = np.searchsorted(token, (at, at + 2048))
        strip = np.zeros((n, 2048), dtype=np.float32)
        strip[owner[lo:hi], token[lo:hi] - at] = 1
        total += strip[rows] @ strip[columns].T
    return total


def trees(sets: list[np.ndarray], labels: list[bytes], threshold: float) -> Iterator[tuple[int, int, float]]:
    """Links (x, y, similarity) of sets in different classes that join all classes similar sets connect: a tree for each, found by
    walking from the first set on. Sets of one class count as connected without a link."""
    n = len(sets)
    sizes = np.array([len(s) for s in sets], dtype=np.float64)
    if n == 2:
        both = np.array([[0.0, len(np.intersect1d(sets[0], sets[1], assume_unique=True))]] * 2)
        both[1] = both[1, ::-1]
    else:
        both = overlaps(sets)
    number = {v: k for k, v in enumerate(dict.fromkeys(labels))}
    own = np.array([number[v] for v in labels])
    reached, open_ = np.zeros(len(number), dtype=bool), np.ones(n, dtype=bool)
    for start in range(n):
        if not open_[start]:
            continue
        reached[own[start]] = True
        todo = np.flatnonzero(own == own[start]).tolist()
        open_[todo] = False
        while todo:
            x = todo.pop(0)
            alike = open_ & (both[x] >= threshold * (sizes + sizes[x]) / (1 + threshold) - 1e-9)
            for y in np.flatnonzero(alike).tolist():
                if not reached[own[y]]:
                    reached[own[y]] = True
                    yield x, y, float(both[x, y] / (sizes[x] + sizes[y] - both[x, y]))
                    more = np.flatnonzero(own == own[y])
                    open_[more] = False
                    todo += more.tolist()


def _draw_first(docs: DataFrame, runs: int, threshold: float, width: int) -> DataFrame:
    """doc_id, uid, sketch, and the tokens drawn in each run (keys, early: of the first runs) of each row's text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for b in batches:
            for ids, uids, sets in _sets(b, hashes, width):
                sizes = np.array([len(s) for s in sets], dtype=np.int64)
                owner, tokens = np.repeat(np.arange(len(sets)), sizes), np.concatenate([np.empty(0, np.uint64), *sets])
                below = np.repeat(np.array([drawn_below(k, threshold) for k in sizes.tolist()], dtype=np.uint64), sizes)
                found = [draws(tokens, r + 1, below) for r in range(runs)]
                whose = owner[np.concatenate([at for at, _ in found])]
                order = np.argsort(whose, kind="stable")
                ends = pa.array(np.concatenate([[0], np.cumsum(np.bincount(whose, minlength=len(sets)))]), pa.int32())
                keys = np.concatenate([k for _, k in found]).view(np.int64)[order]
                early = np.repeat(np.arange(runs) < EARLY, [len(k) for _, k in found])[order]
                lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (keys, early)]
                sketches = [x.tobytes() for x in sketches_of(tokens, owner, len(sets))]
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(uids, pa.binary()), pa.array(sketches, pa.binary()), *lists], names=["doc_id", "uid", "sketch", "keys", "early"])

    return docs.mapInArrow(run, "doc_id long, uid binary, sketch binary, keys array<bigint>, early array<boolean>")


def _draw_next(rows: DataFrame, threshold: float) -> DataFrame:
    """rows: key, uid, tokens. The keys one step further down each path."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            uids, keys = [], []
            for key, uid, tokens in zip(*(b.column(c).to_pylist() for c in ("key", "uid", "tokens"))):
                tokens = np.frombuffer(tokens, dtype=np.uint64)
                _, found = draws(tokens, key, np.uint64(drawn_below(len(tokens), threshold, FURTHER)))
                uids += [uid] * len(found)
                keys.append(found)
            keys = np.concatenate(keys).view(np.int64) if keys else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array([False] * len(keys), pa.bool_()), pa.array(uids, pa.binary())], names=["key", "early", "uid"])

    return rows.mapInArrow(run, "key long, early boolean, uid binary").distinct()


def _meet(drawn: DataFrame) -> DataFrame:
    """key, early, uid, cnt of the draws (key, early, uid, each once) that more than one set made."""
    sizes = stage(drawn.groupBy("key").agg(F.count(F.lit(1)).alias("cnt")).where("cnt > 1"), "sizes")
    met = stage(drawn.join(sizes.hint("merge"), "key"), "met")
    drop_stage(sizes)
    return met


def _leaders(large: DataFrame, labels: DataFrame | None) -> DataFrame:
    """key, early, cnt, uid of a few sets of each bucket: of the first and the last class, and some by hash."""
    rows = _labelled(large, labels)
    picks = [F.min(F.struct("label", "uid"))["uid"], F.max(F.struct("label", "uid"))["uid"], *[F.min(F.struct(F.xxhash64("uid", F.lit(k)).alias("h"), F.col("uid")))["uid"] for k in range(2, LEADERS)]]
    chosen = rows.groupBy("key").agg(F.first("early").alias("early"), F.first("cnt").alias("cnt"), F.array_distinct(F.array(*picks)).alias("uids"))
    return chosen.select("key", "early", "cnt", F.explode("uids").alias("uid"))


def _labelled(rows: DataFrame, labels: DataFrame | None) -> DataFrame:
    """Adds label, the class so far."""
    if labels is None:
        return rows.withColumn("label", F.col("uid"))
    return rows.join(labels.select(F.col("node").alias("uid"), "label").hint("merge"), "uid", "left").withColumn("label", F.coalesce("label", "uid"))


def _blocks(met: DataFrame, leaders: DataFrame | None, limit: int | None = None, block: int | None = None) -> DataFrame:
    """block, early, uid: small buckets whole, larger ones in random parts, each with the bucket's leaders."""
    limit, block = limit or LIMIT, block or BLOCK
    small = met.where(F.col("cnt") <= limit).select(F.xxhash64("key").alias("block"), "early", "uid")
    if leaders is None:
        return small
    parts = F.ceil(F.col("cnt") / block).cast("int")
    dealt = met.where(F.col("cnt") > limit).select(F.xxhash64("key", F.pmod(F.xxhash64("uid", F.lit(3)), parts).cast("int")).alias("block"), "early", "uid")
    led = leaders.select("key", "early", "uid", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part")).select(F.xxhash64("key", "part").alias("block"), "early", "uid")
    return small.unionByName(dealt).unionByName(led)


def _parts(live: DataFrame, labels: DataFrame | None) -> tuple[DataFrame, DataFrame | None]:
    """The sets to compare whole, crowded blocks in parts that share leaders; and the members of those (key: the block)."""
    sizes = stage(live.groupBy("block").agg(F.count(F.lit(1)).alias("cnt")), "crowds")
    if sizes.where(F.col("cnt") > CROWD).isEmpty():
        return live, None
    counted = live.join(sizes.hint("merge"), "block").withColumnRenamed("block", "key")
    crowded = stage(counted.where(F.col("cnt") > CROWD), "crowded")
    leaders = stage(_leaders(crowded, labels), "leaders")
    return stage(_blocks(counted.where(F.col("cnt") <= CROWD), None, CROWD).unionByName(_blocks(crowded, leaders, CROWD, PART)), "parts"), crowded


def _strays(crowded: DataFrame, labels: DataFrame) -> DataFrame:
    """block, early, uid: what is left to compare in crowds that are still in several classes. The members outside the largest class join each part, so
    that they meet everyone; where they are a crowd themselves, the parts meet in pairs."""
    rows = stage(_labelled(crowded, labels), "strays")
    sums = rows.groupBy("key", "label").agg(F.count(F.lit(1)).alias("n"), F.first("cnt").alias("cnt"))
    sums = sums.groupBy("key").agg(F.max_by("label", F.struct("n", "label")).alias("most"), (F.first("cnt") - F.max("n")).alias("strays")).where("strays > 0")
    rows = stage(rows.join(stage(sums, "sums").hint("merge"), "key"), "strays")
    few = rows.where(F.col("strays") <= CROWD)
    leaders = few.where("label <> most").select("key", "early", "cnt", "uid")
    return _blocks(few.withColumn("cnt", F.greatest("cnt", F.lit(CROWD + 1))), leaders, CROWD, PART).unionByName(_all_blocks(rows.where(F.col("strays") > CROWD), PART))


def _all_blocks(met: DataFrame, block: int) -> DataFrame:
    """block, early, uid: larger buckets in all pairs of their parts, so that each two sets meet."""
    rows = met.withColumn("parts", F.ceil(F.col("cnt") / block).cast("int")).withColumn("own", F.pmod(F.xxhash64("uid", F.lit(3)), F.col("parts")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    return rows.select(F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("block"), "early", "uid")


def _with_partners(blocks: DataFrame, sketches: DataFrame, threshold: float) -> DataFrame:
    """block, early, uid of the sets that may have a similar one in their block, by sketches. The block is now a group of them, named by its members: what else
    shared the bucket is not shipped with it, and a group that met in many buckets is compared once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: tuple[list, list, list] = ([], [], [])

        def batch() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.bool_()), pa.array(out[2], pa.binary())], names=["block", "early", "uid"])

        for (_, early), (uids, sketches) in _groups(batches, ["block", "early"], ["uid", "sketch"]):  # one early a block
            once = [k for k, u in enumerate(uids) if not k or u != uids[k - 1]]  # sorted by uid
            if len(once) < 2:
                continue
            matrix = np.frombuffer(b"".join(sketches[k] for k in once), dtype=np.uint16).reshape(len(once), BINS)
            groups: dict[int, list[bytes]] = {}
            for k, group in enumerate(relatives(matrix, threshold).tolist()):
                if group >= 0:
                    groups.setdefault(group, []).append(uids[once[k]])
            for members in groups.values():
                out[0].extend([xxhash.xxh3_64_intdigest(b"".join(members)) - 2**63] * len(members))
                out[1].extend([early] * len(members))
                out[2].extend(members)
            if len(out[0]) > 10_000:
                yield batch()
                out = ([], [], [])
        yield batch()

    rows = blocks.join(sketches.hint("merge"), "uid").select("block", "early", "uid", "sketch")
    rows = rows.repartition("block").sortWithinPartitions("block", "early", "uid").mapInArrow(run, "block long, early boolean, uid binary")
    return rows.groupBy("block", "uid").agg(F.max("early").alias("early")).select("block", "early", "uid")


def _links(live: DataFrame, sets: DataFrame, labels: DataFrame | None, threshold: float) -> DataFrame:
    """a, b, similarity: verified links that join the classes so far, a tree of each block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []

        def batch() -> pa.RecordBatch:
            a, b, similarity = zip(*out) if out else ((), (), ())
            return pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary()), pa.array(similarity, pa.float64())], names=["a", "b", "similarity"])

        for _, (uids, own, tokens) in _groups(batches, ["block"], ["uid", "label", "tokens"]):
            once = [k for k, u in enumerate(uids) if not k or u != uids[k - 1]]  # sorted by uid; a leader may meet itself
            if len(once) > 1:
                out += [(uids[once[x]], uids[once[y]], s) for x, y, s in trees([np.frombuffer(tokens[k], dtype=np.uint64) for k in once], [own[k] for k in once], threshold)]
            if len(out) > 10_000:
                yield batch()
                out = []
        yield batch()

    rows = _labelled(live.select("block", "uid"), labels)
    if labels is not None:
        rows = stage(rows, "labelled")
        rows = rows.join(_mixed(rows, "block").hint("merge"), "block", "left_semi")
    rows = rows.join(sets.hint("merge"), "uid").select("block", "uid", "label", "tokens").repartition("block").sortWithinPartitions("block", "uid")
    ordered = F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")
    return rows.mapInArrow(run, "a binary, b binary, similarity double").select(*ordered, "similarity").distinct()


def similar_in(x: list[np.ndarray], y: list[np.ndarray] | None, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """How many sets of y are similar to each of x, and of x to each of y. Without y: of the other sets of x, and nothing."""
    if y is None and len(x) == 2:
        shared = len(np.intersect1d(*x, assume_unique=True))
        alike = int(shared >= threshold * (len(x[0]) + len(x[1])) / (1 + threshold) - 1e-9)
        return np.array([alike, alike]), np.zeros(0, dtype=np.int64)
    n = len(x)
    sizes = np.array([len(s) for s in (*x, *(y or ()))], dtype=np.float64)
    if y is None:
        shared, left, right = overlaps(x), sizes, sizes
    else:
        shared, left, right = overlaps([*x, *y], n), sizes[:n], sizes[n:]
    alike = shared >= threshold * (left[:, None] + right) / (1 + threshold) - 1e-9
    if y is None:
        np.fill_diagonal(alike, False)
        return alike.sum(axis=1), np.zeros(0, dtype=np.int64)
    return alike.sum(axis=1), alike.sum(axis=0)


def _all_links(labels: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """uid, similar: how many other texts are similar to each text of a class. Similar texts are in one class, so each pair of a class is
    compared once: classes up to WHOLE texts in one task, larger ones in all pairs of their parts."""
    sizes = stage(labels.groupBy("label").agg(F.count(F.lit(1)).alias("cnt")).where("cnt > 1"), "sizes")
    rows = labels.select(F.col("node").alias("uid"), "label").join(sizes.hint("merge"), "label")
    parts = F.when(F.col("cnt") <= WHOLE, 1).otherwise(F.ceil(F.col("cnt") / (WHOLE // 2))).cast("int")
    rows = rows.withColumn("parts", parts).withColumn("own", F.pmod(F.xxhash64("uid", F.lit(3)), F.col("parts")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    rows = rows.select(F.xxhash64("label", F.least("own", "other"), F.greatest("own", "other")).alias("block"), F.signum(F.col("own").cast("double") - F.col("other")).cast("int").alias("side"), "uid")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (sides, uids, tokens) in _groups(batches, ["block"], ["side", "uid", "tokens"]):  # side 0: a part with itself; -1 and 1: one with another
            held = [np.frombuffer(s, dtype=np.uint64) for s in tokens]
            n = sum(s <= 0 for s in sides)
            if sides[0] == 0 or n in (0, len(held)):
                if sides[0] or len(held) < 2:
                    continue
                found = similar_in(held, None, threshold)
            else:
                found = similar_in(held[:n], held[n:], threshold)
            yield pa.RecordBatch.from_arrays([pa.array(uids, pa.binary()), pa.array(np.concatenate(found).astype(np.int64))], names=["uid", "similar"])

    rows = rows.join(sets.hint("merge"), "uid").select("block", "side", "uid", "tokens").repartition("block").sortWithinPartitions("block", "side", "uid")
    return rows.mapInArrow(run, "uid binary, similar long").groupBy("uid").agg(F.sum("similar").alias("similar"))


def _mixed(rows: DataFrame, key: str) -> DataFrame:
    """The keys whose sets are in more than one class."""
    return stage(rows.groupBy(key).agg(F.min("label").alias("low"), F.max("label").alias("high")).where("low <> high").select(key), "mixed")


def similarity_classes(docs: DataFrame, threshold: float = MIN_SIMILARITY, width: int = SHINGLE_WORDS, recall: float = 0.999, every: bool = False) -> DataFrame:
    """One row per row of docs (doc_id, text): doc_id, text_id (least id with the same words; the text's representative),
    class_id (least id of the texts that similarities of at least the threshold connect), n_links (links of the text that were
    verified and kept, and its other copies), link_id and link_similarity (one of the kept links: the text_id of a text whose exact
    similarity with this one is at least the threshold; null without any). Kept links connect each class; links that follow
    from them inside a class are not listed. every: n_links counts all similar texts, listed or not, and the other copies: each pair of a class is
    compared, which is square in a class, spread over tasks."""
    runs = runs_for(recall)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    first = stage(_draw_first(rows, runs, threshold, width), "first")
    ids = first.select("doc_id", "uid")
    each = [F.first(c).alias(c) for c in ("sketch", "keys", "early")]
    texts = stage(first.where("uid is not null").groupBy("uid").agg(F.min("doc_id").alias("text_id"), F.count(F.lit(1)).alias("copies"), *each), "texts")
    sketches = texts.select("uid", "sketch")
    met = _meet(texts.select("uid", F.inline(F.arrays_zip("keys", "early")).alias("key", "early")).select("key", "early", "uid"))
    release(rows.sparkSession)
    edges, labels, sets = [], None, None
    for depth in range(DEPTH + 1):
        large = met.where(F.col("cnt") > LIMIT)
        large = None if large.isEmpty() else large
        last, leaders = depth == DEPTH, None
        if large is not None and not last:
            leaders = stage(_leaders(large, labels), "leaders")
        blocks = _blocks(met, leaders)
        if large is not None and last:
            blocks = blocks.unionByName(_all_blocks(large, BLOCK))
        live = stage(_with_partners(blocks, sketches, threshold), "live")
        if sets is None:  # the texts of all later steps are live or in a large bucket here
            known = live.select("uid") if large is None else live.select("uid").unionByName(large.select("uid"))
            wanted = stage(texts.select("uid", "text_id").join(known.distinct().hint("merge"), "uid", "left_semi"), "wanted")
            sets = stage(_token_sets(rows, wanted, width), "sets")
            drop_stage(wanted)
            release(rows.sparkSession)
        parts, crowded = _parts(live, labels)
        for early in (True, False) if depth == 0 else (False,):
            found = stage(_links(parts.where(F.col("early") == early), sets, labels, threshold), "links")
            edges.append(found)
            if labels is None or not found.isEmpty():
                labels = merge_labels(labels, found.select("a", "b"))
        if crowded is not None:
            rest = _strays(crowded, labels)
            if not rest.isEmpty():
                edges.append(stage(_links(rest, sets, labels, threshold), "links"))
                labels = merge_labels(labels, edges[-1].select("a", "b"))
        release(rows.sparkSession)
        if large is None or last:
            break
        rest = stage(_labelled(large.select("key", "uid"), labels), "rest")
        rest = rest.join(_mixed(rest, "key").hint("merge"), "key", "left_semi").join(leaders.select("key", "uid").hint("merge"), ["key", "uid"], "left_anti").select("key", "uid")
        drawn = stage(_draw_next(rest.join(sets.hint("merge"), "uid").select("key", "uid", "tokens"), threshold), "drawn")
        drop_stage(met)
        met = _meet(drawn)
        if met.isEmpty():
            break
    drop_stage(met)
    similar = stage(_all_links(labels, sets, threshold), "similar") if every else None
    drop_stage(sets)
    links = edges[0]
    for more in edges[1:]:
        links = links.unionByName(more)
    both = links.select(F.col("a").alias("uid"), F.col("b").alias("other"), "similarity").unionByName(links.select(F.col("b").alias("uid"), F.col("a").alias("other"), "similarity"))
    both = both.groupBy("uid").agg(F.min(F.struct("other", "similarity")).alias("one"), F.countDistinct("other").alias("links"))
    linked = texts.join(labels.select(F.col("node").alias("uid"), "label"), "uid")
    heads = linked.groupBy("label").agg(F.min("text_id").alias("class_id"))
    linked = linked.join(both, "uid").select("uid", "label", "links", F.col("one.other").alias("other"), F.col("one.similarity").alias("link_similarity"))
    linked = stage(linked, "linked").join(stage(heads, "heads").hint("merge"), "label").join(texts.select(F.col("uid").alias("other"), F.col("text_id").alias("link_id")).hint("merge"), "other")
    classes = texts.join(linked.select("uid", "class_id", "links", "link_id", "link_similarity"), "uid", "left").where("copies > 1 or class_id is not null")
    if every:
        classes = classes.join(similar.hint("merge"), "uid", "left")
    n_links = (F.coalesce("similar" if every else "links", F.lit(0)) + F.col("copies") - 1).cast("long").alias("n_links")
    classes = stage(classes.select(F.col("uid").alias("key"), "text_id", F.coalesce("class_id", "text_id").alias("class_id"), n_links, "link_id", "link_similarity"), "classes")
    own = F.coalesce(F.col("uid"), F.unhex(F.md5(F.concat(F.lit("none"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))))
    out = ids.withColumn("key", own).join(classes.hint("merge"), "key", "left")
    return out.select("doc_id", F.coalesce("text_id", "doc_id").alias("text_id"), F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), "link_id", "link_similarity")


def _candidate_filter(wanted: DataFrame) -> np.ndarray:
    """Bloom filter of the text_ids: FILTER_BITS bits, whatever their number; when full it passes all rows to the join."""
    slots = wanted.select(F.explode(F.array(*_slots(F.col("text_id")))).alias("slot"))
    words = slots.groupBy(F.shiftright("slot", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, int(slot & 63)))").alias("bits")).toArrow()
    out = np.zeros(FILTER_BITS // 64, dtype=np.int64)
    out[words.column("word").to_numpy()] = words.column("bits").to_numpy()
    return out.view(np.uint64)


def _slots(value: Column) -> list[Column]:
    return [F.pmod(F.xxhash64(value, F.lit(k)), F.lit(FILTER_BITS)) for k in (1, 2)]


def _token_sets(rows: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """uid, tokens (sorted hashes) of each text in wanted (uid, text_id), from the rows with its least id."""
    passing = rows.sparkSession.sparkContext.broadcast(_candidate_filter(wanted))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, bits = WordHashes(), passing.value
        for b in batches:
            hit = np.ones(b.num_rows, dtype=bool)
            for c in ("slot_1", "slot_2"):
                slot = b.column(c).to_numpy()
                hit &= (bits[slot >> 6] >> (slot & 63).astype(np.uint64)) & np.uint64(1) == 1
            for ids, uids, sets in _sets(b.filter(pa.array(hit)), hashes, width):
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(uids, pa.binary()), pa.array([s.tobytes() for s in sets], pa.binary())], names=["row_id", "uid", "tokens"])

    one, two = _slots(F.col("doc_id"))
    sets = rows.select("doc_id", "text", one.alias("slot_1"), two.alias("slot_2")).mapInArrow(run, "row_id long, uid binary, tokens binary")
    sets = wanted.hint("merge").join(sets, "uid").where("row_id <=> text_id")
    return sets.groupBy("uid").agg(F.first("tokens").alias("tokens"))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs whose doc_id is their class's id: one document of each class stays, with the columns of docs.
    Rows that repeat a doc_id with equal words are one document; texts without words all stay."""
    stay = similarity_classes(docs, **options).where("doc_id <=> class_id").select(F.col("doc_id").alias("stay_id")).distinct()
    kept = docs.join(stay, F.col("doc_id").eqNullSafe(F.col("stay_id"))).drop("stay_id")
    return kept
