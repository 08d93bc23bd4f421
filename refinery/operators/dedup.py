"""Deduplication: exact, character n-gram MinHash, embeddings with a persistent index, and across collections."""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from refinery.functions import text as tx
from refinery.operators.graph import components, first_independent_set
from refinery.operators.storage import few, materialize, release, remove
from refinery.records import reject, undecided

SEP = "\x1f"


def dedup_text() -> Column:
    """The text that makes a record a duplicate, by task type."""
    join = lambda *c: F.concat_ws(SEP, *[F.coalesce(x, F.lit("")) for x in c])
    i, o = F.col("instruction"), F.col("output")
    kind = F.col("task_type")
    return F.when(kind == "preference", join(i, o, F.col("chosen"), F.col("rejected"))).when(kind == "grpo", join(i, F.concat_ws(SEP, F.coalesce(F.col("responses"), F.array())))).when(kind == "language_modeling", F.coalesce(o, F.lit(""))).otherwise(join(i, o))


def exact_key(text: Column) -> Column:
    return F.sha2(tx.normal_form(text), 256)


def exact_survivors(keys: DataFrame) -> DataFrame:
    """keys: id, key. Returns key, survivor (least id), n. Only keys and ids are shuffled, pre-aggregated by task."""
    return keys.groupBy("key").agg(F.min("id").alias("survivor"), F.count(F.lit(1)).alias("n"))


def dedup_exact(df: DataFrame, text: Column | None = None) -> DataFrame:
    """Keeps the record with the least id of each normal form; marks the others with the survivor's id."""
    keys = undecided(df).select("id", exact_key(dedup_text() if text is None else text).alias("key"))
    best = materialize(exact_survivors(keys).where("n > 1"), "exact")
    # ids and keys alone meet, so a text that many share moves no texts; the join has plain exchanges on both sides, which a hot key can be split over
    gone = keys.join(best.hint("merge"), "key").where(F.col("id") != F.col("survivor")).select(F.col("id").alias("_id"), F.col("survivor").alias("_best"))
    df = df.join(few(materialize(gone, "copies")), F.col("id") == F.col("_id"), "left")
    return reject(df, F.col("_best").isNotNull(), "exact_duplicate", "dedup_exact", F.col("_best")).drop("_id", "_best")


def band_curve(s: float, bands: int, rows: int) -> float:
    """Probability that a pair of similarity s shares a band."""
    return 1 - (1 - s**rows) ** bands


def choose_bands(num_perm: int = 128, threshold: float = 0.85, fp_weight: float = 0.5, steps: int = 200) -> tuple[int, int]:
    """The bands and rows with the least weighted area of false positives below and false negatives above the threshold."""
    best = (math.inf, 1, num_perm)
    for rows in range(1, num_perm + 1):
        for bands in range(1, num_perm // rows + 1):
            fp = sum(band_curve(threshold * (k + 0.5) / steps, bands, rows) for k in range(steps)) * threshold / steps
            fn = sum(1 - band_curve(threshold + (1 - threshold) * (k + 0.5) / steps, bands, rows) for k in range(steps)) * (1 - threshold) / steps
            best = min(best, (fp_weight * fp + (1 - fp_weight) * fn, bands, rows))
    return best[1], best[2]


def run_bands(num_perm: int, threshold: float, recall: float = 0.99) -> tuple[int, int]:
    """The most rows a band, so the fewest candidates, with which a pair at the threshold meets with a probability of `recall` at least."""
    rows = next((r for r in range(num_perm, 0, -1) if 1 - (1 - threshold**r) ** (num_perm // r) >= recall), 1)
    return num_perm // rows, rows


def _mixed(h: np.ndarray) -> np.ndarray:
    """Multiply and shift rounds, so that near codes get unrelated hashes."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


#: n-grams from which on the texts at hand are signed together, which bounds the table of hashes.
SIGNED = 1 << 18


def signatures(df: DataFrame, n: int, num_perm: int, bands: int, rows: int, seed: int = 1) -> DataFrame:
    """df: id, text. Returns id, buckets (a hash for each band), size (distinct n-grams), parity. Signatures are built in numpy, some texts at a time.

    parity: bits, as many as the next power of two from the size on, of which each tells whether an odd number of the text's n-grams falls on it. Two texts differ
    in at least as many n-grams as bits."""
    rng = np.random.default_rng(seed)
    a = rng.integers(1, 2**61, num_perm, dtype=np.uint64) | np.uint64(1)
    b = rng.integers(0, 2**61, num_perm, dtype=np.uint64)

    def hashed(characters: list[np.ndarray]) -> np.ndarray:
        grams = np.zeros(len(characters[0]), np.uint64)
        for c in characters:
            grams = grams * np.uint64(0x100000001B3) + c
        return grams

    def lows(held: list[np.ndarray]) -> np.ndarray:
        """The least hash of each text's n-grams by each permutation. An n-gram is hashed once, however often the texts hold it."""
        known, at = np.unique(np.concatenate(held), return_inverse=True)
        known, starts = _mixed(known), np.cumsum([0, *(len(g) for g in held[:-1])])
        low = np.empty((len(held), bands * rows), np.uint64)
        for k in range(bands * rows):
            low[:, k] = np.minimum.reduceat(_mixed(known * a[k] + b[k])[at], starts)
        return low

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for batch in batches:
            buckets, sizes, parities, held = [], [], [], []
            texts = [t or "" for t in batch.column("text").to_pylist()]
            for at, t in enumerate(texts):
                own = gram_codes(t, n)  # those that pairs are verified by
                if len(t) < n:
                    held.append(np.array([xxhash.xxh3_64_intdigest(t.encode("utf-8", "surrogatepass"))], dtype=np.uint64))
                elif n <= 3:  # the distinct codes hold the characters
                    held.append(hashed([own >> np.uint64(21 * k) & np.uint64(0x1FFFFF) for k in reversed(range(n))]))
                else:
                    codes = np.frombuffer(t.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
                    held.append(distinct(hashed([codes[k : len(codes) - n + 1 + k] for k in range(n)])))
                sizes.append(len(own))
                parities.append(parity(own))
                if at + 1 == len(texts) or sum(map(len, held)) >= SIGNED:
                    buckets += [[xxhash.xxh3_64_intdigest(s) - 2**63 for s in sig] for sig in lows(held).reshape(len(held), bands, rows)]
                    held = []
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(buckets, pa.list_(pa.int64())), pa.array(sizes, pa.int64()), pa.array(parities, pa.binary())], names=["id", "buckets", "size", "parity"])

    return df.where("id is not null").select("id", "text").mapInArrow(run, f"id {df.schema['id'].dataType.simpleString()}, buckets array<long>, size long, parity binary")


#: Least and most bits of a parity; members of a bucket that are compared in one task; rows of them that are compared at once.
FEWEST_BITS, MOST_BITS, WIDE, ROWS = 256, 4_096, 2_048, 256


def parity(grams: np.ndarray) -> bytes:
    bits = min(MOST_BITS, max(FEWEST_BITS, 1 << (len(grams) - 1).bit_length()))
    odd = np.bincount((_mixed(grams) & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def _folded(words: np.ndarray) -> np.ndarray:
    """Parities of half as many bits: a bit of the second half falls on its place in the first."""
    half = words.shape[1] // 2
    return words[:, :half] ^ words[:, half:]


def bucket_mates(keys: np.ndarray, sizes: np.ndarray, parities: list[bytes], own: np.ndarray, crossed: bool, threshold: float, prune: bool) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (positions) of a bucket's members that can reach the threshold by their sizes and, if asked to prune, by their parities: of two sets with D n-grams
    in one alone, (|x| + |y| - D) / (|x| + |y| + D) is the similarity. crossed: only pairs of two blocks (own) are wanted."""
    order = np.argsort(sizes, kind="stable")
    size, held, block = sizes[order].astype(np.float64), [parities[k] for k in order], own[order]
    widths = np.array([len(x) for x in held])
    words = {w: np.frombuffer(b"".join(held[k] for k in np.flatnonzero(widths == w)), np.uint64).reshape(-1, w // 8) for w in set(widths.tolist())}
    left, right = [], []
    for w, mine in words.items():
        at = np.flatnonzero(widths == w)
        for other in (w, 2 * w) if prune else words:
            if other not in words:
                continue
            to = np.flatnonzero(widths == other)
            theirs = mine if other == w else (_folded(words[other]) if prune else words[other])
            for k in range(0, len(at), ROWS):
                x = at[k : k + ROWS]
                # sizes ascend: no partner beyond the largest size that the last row of the strip admits
                first, last = (np.searchsorted(to, x[0] + 1), np.searchsorted(size[to], size[x[-1]] / threshold * (1 + 1e-9), "right")) if threshold > 0 else (np.searchsorted(to, x[0] + 1), len(to))
                if first >= last:
                    continue
                y = to[first:last]
                fits = (x[:, None] < y[None, :]) & (size[x][:, None] >= threshold * size[y][None, :])
                if crossed:
                    fits &= block[x][:, None] != block[y][None, :]
                i, j = np.nonzero(fits)
                if prune and len(i):
                    apart = np.zeros(len(i), np.int64)
                    for c in range(mine.shape[1]):
                        apart += np.bitwise_count(mine[k + i, c] ^ theirs[first + j, c])
                    both = size[x[i]] + size[y[j]]
                    near = both - apart >= threshold * (both + apart) - 1e-6
                    i, j = i[near], j[near]
                left.append(order[x[i]])
                right.append(order[y[j]])
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *left]), np.concatenate([none, *right])


def candidate_pairs(signed: DataFrame, wide: int = WIDE, threshold: float = 0.0, prune: bool = True) -> DataFrame:
    """Distinct pairs a < b that share a bucket, without those whose sizes or parities alone keep them below the threshold: what is pruned can't reach it. A bucket of
    more than `wide` members is dealt out in blocks; no pair is lost. The members of a bucket meet by a number and their parity, once a band, and only those of the pairs
    that stay are told by their ids."""
    signed = materialize(signed.withColumn("k", F.monotonically_increasing_id()), "signatures")
    member = lambda *more: signed.select("k", "size", *more, F.posexplode("buckets").alias("band", "bucket"))
    sizes = materialize(signed.select(F.posexplode("buckets").alias("band", "bucket")).groupBy("band", "bucket").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > wide), "wide")
    dealt = member("parity")
    if sizes.isEmpty():
        dealt = dealt.withColumns({"i": F.lit(0), "j": F.lit(0), "own": F.lit(0)})
    else:  # a wide bucket is compared whole, in blocks dealt out to tasks
        dealt = dealt.join(few(sizes), ["band", "bucket"], "left").withColumn("blocks", F.coalesce(F.ceil(F.col("n") / wide), F.lit(1)).cast("int"))
        dealt = dealt.withColumn("own", F.pmod(F.xxhash64("k"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        dealt = dealt.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
    dealt = dealt.select("band", "bucket", "i", "j", "own", "k", "size", "parity").repartition("band", "bucket", "i", "j").sortWithinPartitions("bucket", "band", "i", "j")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        none = pa.RecordBatch.from_arrays([pa.array([], pa.int64())] * 2, names=["x", "y"])

        def met(columns: list[np.ndarray], bits: list[bytes], edges: list[int]) -> pa.RecordBatch:
            _, _, i, j, k, size, own = columns
            found = []
            for at, end in zip(edges, edges[1:]):
                if end - at > 1:
                    x, y = bucket_mates(k[at:end], size[at:end], bits[at:end], own[at:end], i[at] != j[at], threshold, prune)
                    if len(x):
                        found.append((k[at + x], k[at + y]))
            if not found:
                return none
            x, y = map(np.concatenate, zip(*found))
            return pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["x", "y"])

        columns, bits = None, []
        for batch in batches:
            more = [batch.column(c).to_numpy() for c in ("band", "bucket", "i", "j", "k", "size", "own")]
            columns = more if columns is None else [np.concatenate(c) for c in zip(columns, more)]
            bits += batch.column("parity").to_pylist()
            new = np.zeros(max(len(bits) - 1, 0), bool)
            for c in columns[:4]:
                new |= c[1:] != c[:-1]
            edges = [0, *(np.flatnonzero(new) + 1).tolist()]
            yield met(columns, bits, edges)
            columns, bits = [c[edges[-1] :] for c in columns], bits[edges[-1] :]  # the last bucket may go on
        if bits:
            yield met(columns, bits, [0, len(bits)])

    pairs = materialize(dealt.mapInArrow(run, "x long, y long").distinct(), "mates")
    names = lambda at, to: few(signed.select(F.col("k").alias(at), F.col("id").alias(to)).join(few(pairs.select(at).distinct()), at, "left_semi"))
    named = pairs.join(names("x", "p"), "x").join(names("y", "q"), "y")
    named = materialize(named.where("p <> q").select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b")).distinct(), "pairs")
    for table in (signed, sizes, pairs):
        remove(table)
    release(signed.sparkSession)  # the shuffles of what is written by now
    return named


#: Texts of a part on average, so half of those that a task holds at once while it verifies pairs: the more, the fewer parts a text is shipped to.
PART = 1_024


def with_first(df: DataFrame) -> DataFrame:
    """df: id, text (in normal form). Returns id, first: the least id of the same text. Hashes are shuffled, no texts."""
    keys = materialize(df.select("id", F.md5(F.coalesce("text", F.lit(""))).alias("key")), "keys")
    firsts = keys.groupBy("key").agg(F.min("id").alias("first"))
    return materialize(keys.join(firsts.hint("merge"), "key").select("id", "first"), "firsts")


def distinct_pairs(df: DataFrame, n: int, threshold: float, num_perm: int, bands: tuple[int, int] | None, verify: bool) -> DataFrame:
    """near_pairs of texts that all differ."""
    b, r = bands or run_bands(num_perm, threshold)
    pairs = candidate_pairs(signatures(df, n, max(num_perm, b * r), b, r), threshold=threshold, prune=verify)
    return verified(pairs, df, n, threshold) if verify else pairs.withColumn("similarity", F.lit(None).cast("double"))


#: Pairs of a block up to which sets are met one by one; n-grams that are numbered, cells of a table of bits and words of it that are gathered at once.
FEW_PAIRS, NUMBERED, CELLS, WORDS = 8, 1 << 21, 1 << 25, 1 << 18


def shared_grams(grams: list[np.ndarray], x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """How many n-grams the sets x[k] and y[k] have in common: sets as rows of bits, a column for each n-gram that several of them hold. Counts add up over slices
    of the n-grams, which bound the memory."""
    if len(x) <= FEW_PAIRS:
        return np.array([len(np.intersect1d(grams[p], grams[q], assume_unique=True)) for p, q in zip(x, y)], np.int64)
    shared, slices = np.zeros(len(x), np.int64), -(-sum(map(len, grams)) // NUMBERED)
    for part in range(slices):
        mine = grams if slices == 1 else [g[g % np.uint64(slices) == part] for g in grams]
        _, at, held = np.unique(np.concatenate(mine), return_inverse=True, return_counts=True)
        several = held > 1
        stay, column, width = several[at], np.cumsum(several) - 1, int(several.sum())
        row, at = np.repeat(np.arange(len(mine)), [len(g) for g in mine])[stay], column[at[stay]]
        columns = max(64, CELLS // len(mine) // 64 * 64)
        for first in range(0, width, columns):
            inside = (at >= first) & (at < first + columns)
            table = np.zeros((len(mine), min(columns, -(-(width - first) // 64) * 64)), bool)
            table[row[inside], at[inside] - first] = True
            words = np.packbits(table, axis=1).view(np.uint64)
            step = max(1, WORDS // words.shape[1])
            for k in range(0, len(x), step):
                shared[k : k + step] += np.bitwise_count(words[x[k : k + step]] & words[y[k : k + step]]).sum(axis=1, dtype=np.int64)
    return shared


def verified(pairs: DataFrame, df: DataFrame, n: int, threshold: float) -> DataFrame:
    """a, b, similarity of the pairs (a, b) whose texts in df reach the threshold. Each component of the pairs is verified in one task, so that a text is shipped
    once however many pairs it is in; a component of more than 2 PART texts is dealt to parts, and its pairs to pairs of parts."""
    labels = components(pairs)
    sizes = labels.groupBy("label").agg(F.count(F.lit(1)).alias("n"))
    parts = F.when(F.col("n") <= 2 * PART, 1).otherwise(F.ceil(F.col("n") / PART))
    of = materialize(labels.join(sizes.hint("merge"), "label").select("node", "label", F.pmod(F.xxhash64("node"), parts).alias("part")), "parts")
    remove(labels)
    side = lambda s: of.select(F.col("node").alias(s), F.col("label").alias(f"label_{s}"), F.col("part").alias(f"part_{s}"))
    low, high = F.least("part_a", "part_b"), F.greatest("part_a", "part_b")
    dealt = materialize(pairs.join(side("a").hint("merge"), "a").join(side("b").hint("merge"), "b").select(F.xxhash64("label_a", low, high).alias("block"), "a", "b"), "dealt")
    remove(of)
    release(df.sparkSession)
    asked = dealt.select("block", F.col("a").alias("id")).unionByName(dealt.select("block", F.col("b").alias("id"))).distinct()
    kind = df.schema["id"].dataType.simpleString()
    texts = asked.join(df.select("id", "text").hint("merge"), "id").select("block", F.col("id").alias("a"), F.lit(None).cast(kind).alias("b"), "text")
    rows = texts.unionByName(dealt.select("block", "a", "b", F.lit(None).cast("string").alias("text"))).repartition("block").sortWithinPartitions("block", F.col("b").asc_nulls_first())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, places, grams, asked = None, {}, [], []

        def told(types: tuple) -> pa.RecordBatch:
            ids, (x, y) = list(places), np.array(asked, np.int64).reshape(-1, 2).T
            size = np.array([len(g) for g in grams], np.int64)
            fits = np.minimum(size[x], size[y]) >= threshold * np.maximum(size[x], size[y])
            x, y = x[fits], y[fits]
            shared = shared_grams(grams, x, y)
            alike = shared / (size[x] + size[y] - shared)
            near = alike >= threshold
            of = pa.array(ids, types[0])
            return pa.RecordBatch.from_arrays([of.take(pa.array(x[near])), of.take(pa.array(y[near])), pa.array(alike[near])], names=["a", "b", "similarity"])

        types = (None,)
        for batch in batches:
            types = (batch.schema.field("a").type,)
            for block, a, b, text in zip(*(batch.column(c).to_pylist() for c in ("block", "a", "b", "text"))):
                if block != now:
                    if asked:
                        yield told(types)
                    now, places, grams, asked = block, {}, [], []
                if b is None:  # the texts of a block come before its pairs
                    places[a] = len(grams)
                    grams.append(gram_codes(text or "", n))
                else:
                    asked.append((places[a], places[b]))
        if asked:
            yield told(types)

    return rows.mapInArrow(run, f"a {kind}, b {kind}, similarity double")


def near_pairs(df: DataFrame, n: int = 3, threshold: float = 0.85, num_perm: int = 128, bands: tuple[int, int] | None = None, verify: bool = True) -> DataFrame:
    """df: id, text (in normal form). Returns a, b, similarity of the pairs found by banding; verified exactly unless told not to. Equal texts are compared as one and
    written out as pairs at the end."""
    first = with_first(df)
    alone = df.join(few(first.where("id <> first").select("id")), "id", "left_anti")
    pairs = materialize(distinct_pairs(alone, n, threshold, num_perm, bands, verify), "similar")
    several = materialize(first.join(first.groupBy("first").count().where("count > 1").select("first").hint("merge"), "first"), "several")
    equal = several.alias("x").join(several.alias("y").hint("merge"), (F.col("x.first") == F.col("y.first")) & (F.col("x.id") < F.col("y.id")))
    equal = equal.select(F.col("x.id").alias("a"), F.col("y.id").alias("b"), F.lit(1.0 if verify else None).cast("double").alias("similarity"))
    for c in ("a", "b"):  # each text of a pair stands for all its copies
        pairs = pairs.join(several.select(F.col("first").alias(c), F.col("id").alias("copy")).hint("merge"), c, "left").withColumn(c, F.coalesce("copy", c)).drop("copy")
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "similarity").unionByName(equal)


def gram_codes(text: str, n: int) -> np.ndarray:
    """Sorted distinct codes of a text's character n-grams: exact up to three characters (21 bits each), hashed beyond. A shorter text is one gram."""
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    n = max(1, min(n, len(codes)))
    out = np.zeros(max(len(codes) - n + 1, 1), dtype=np.uint64)
    if len(codes):
        for k in range(n):
            out = (out << np.uint64(21) if n <= 3 else out * np.uint64(0x9E3779B97F4A7C15)) + codes[k : len(codes) - n + 1 + k]
    return distinct(out)


def distinct(values: np.ndarray) -> np.ndarray:
    """The values once each, ascending; the array itself is sorted."""
    values.sort()
    new = np.ones(len(values), bool)
    np.not_equal(values[1:], values[:-1], out=new[1:])
    return values[new]


def dedup_minhash(df: DataFrame, n: int = 3, threshold: float = 0.85, num_perm: int = 128, policy: str = "greedy", bands: tuple[int, int] | None = None, verify: bool = True, text: Column | None = None) -> DataFrame:
    """Marks near-duplicates of a kept record. greedy: as inserting in id order; component: the least id of each component stays."""
    keys = undecided(df).select("id", tx.normal_form(dedup_text() if text is None else text).alias("text"))
    first = with_first(keys)
    alone = keys.join(few(first.where("id <> first").select("id")), "id", "left_anti")
    edges = distinct_pairs(alone, n, threshold, num_perm, bands, verify).select("a", "b")
    if policy == "greedy":
        gone = first_independent_set(edges).where("not kept").select(F.col("node").alias("id"), F.col("by").alias("_by"))
    else:
        gone = components(edges).where("node <> label").select(F.col("node").alias("id"), F.col("label").alias("_by"))
    # a copy goes with the first of its text, or for it
    gone = first.join(gone.select(F.col("id").alias("first"), "_by").hint("merge"), "first", "left").select("id", F.coalesce("_by", F.when(F.col("id") != F.col("first"), F.col("first"))).alias("_by")).where("_by is not null")
    df = df.join(few(materialize(gone, "gone")), "id", "left")
    return reject(df, F.col("_by").isNotNull(), "near_duplicate", "dedup_minhash", F.col("_by")).drop("_by")


#: Vectors up to which `auto` compares all blocks; beyond, each vector would be copied more than a few times.
EXACT_VECTORS = 4_096
#: Most vectors in a block of the exact comparison; rows of it that are multiplied at once.
WIDEST_BLOCK, STRIP = 4_096, 512


def vector_pairs(new: DataFrame, old: DataFrame | None, threshold: float, index: str = "auto", tables: int = 12, bits: int = 8, dim: int = 64, block: int = 512) -> DataFrame:
    """Pairs a, b (ids; a < b within `new`, a from `old` otherwise) with cosine above the threshold; id, embedding columns.

    exact: blocks of vectors meet in pairs, each compared in one task by a matrix product. lsh: signs of random projections bucket the vectors, and
    only bucket mates are compared, in `tables` tables whose width makes a pair at the threshold meet with 0.95 at least (`sign_bits`). auto: exact up to
    EXACT_VECTORS vectors, the index beyond."""
    side = new.select("id", "embedding", F.lit(1).alias("side"))
    if old is not None:
        side = side.unionByName(old.select("id", "embedding", F.lit(0).alias("side")))
    kind = new.schema["id"].dataType.simpleString()
    if index == "auto":
        index = "exact" if side.count() <= EXACT_VECTORS else "lsh"
        bits = sign_bits(threshold, tables) if index == "lsh" else bits
    if index == "exact":
        n = side.count()
        n_blocks = max(1, math.ceil(n / min(WIDEST_BLOCK, max(block, n // 8))))  # each vector is copied once a block
        dealt = side.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(n_blocks)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(n_blocks - 1))))
        dealt = dealt.select(F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "id", "embedding", "side")
        keys = ["i", "j"]
    else:
        planes = np.random.default_rng(7).standard_normal((tables * bits, dim)).astype(np.float32)
        weights = 1 << np.arange(bits, dtype=np.int64)

        def signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                m = _matrix(b.column("embedding"))
                codes = ((m @ planes[:, : m.shape[1]].T >= 0).reshape(b.num_rows, tables, bits) * weights).sum(axis=2)
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("id", "embedding", "side")), pa.ListArray.from_arrays(np.arange(b.num_rows + 1, dtype=np.int32) * tables, codes.ravel().astype(np.int64))], names=["id", "embedding", "side", "codes"])

        # a vector is written once, and goes once for each table to the buckets that it shares with others
        held = materialize(side.mapInArrow(signed, f"id {kind}, embedding array<float>, side int, codes array<long>"), "codes")
        sizes = held.select(F.posexplode("codes").alias("table", "code")).groupBy("table", "code").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        sizes = materialize(sizes.select("table", "code", F.ceil(F.col("n") / F.least(F.lit(WIDEST_BLOCK), F.greatest(F.lit(block), F.col("n") / 8))).cast("int").alias("blocks")), "codes-shared")
        dealt = held.select("id", "embedding", "side", F.posexplode("codes").alias("table", "code")).join(few(sizes), ["table", "code"])
        dealt = dealt.withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        dealt = dealt.select("table", "code", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "id", "embedding", "side")
        keys = ["table", "code", "i", "j"]

    def compare(key: tuple, table: pa.Table) -> pa.Table:
        m = _matrix(table.column("embedding").combine_chunks()).astype(np.float64)
        m /= np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12)
        ids, own, s = np.array(table.column("id").to_pylist()), table.column("own").to_numpy(), table.column("side").to_numpy()
        key, found = [k.as_py() for k in key], []
        for at in range(0, len(m), STRIP):
            x, y = np.nonzero(m[at : at + STRIP] @ m.T > threshold)
            x += at
            # later rows are checked against earlier ones: old before new, then by id
            first = (s[x] < s[y]) | ((s[x] == 1) & (s[y] == 1) & (ids[x] < ids[y]))
            keep = first & ((key[-2] == key[-1]) | (own[x] != own[y]))
            x, y = x[keep], y[keep]
            found.append((x, y, s[x] == 0, np.einsum("ij,ij->i", m[x], m[y])))
        x, y, old, cosine = (np.concatenate(parts) for parts in zip(*found))
        of = table.column("id").combine_chunks()
        return pa.table({"a": of.take(pa.array(x)), "b": of.take(pa.array(y)), "old": old, "cosine": cosine})

    return dealt.groupBy(*keys).applyInArrow(compare, f"a {kind}, b {kind}, old boolean, cosine double").dropDuplicates(["a", "b", "old"])


def _matrix(vectors: pa.Array) -> np.ndarray:
    """The rows of an array of lists of one length, without a Python object for each number."""
    return np.asarray(vectors.flatten().to_numpy(zero_copy_only=False), dtype=np.float32).reshape(len(vectors), -1)


def sign_bits(threshold: float, tables: int, recall: float = 0.95) -> int:
    """The most signs a table, so the fewest candidates, with which a pair at the cosine threshold shares a table with a probability of `recall`."""
    agree = 1 - math.acos(min(1.0, max(-1.0, threshold))) / math.pi
    return next((b for b in range(24, 0, -1) if 1 - (1 - agree**b) ** tables >= recall), 1)


class IndexStore:
    """Accepted vectors of earlier runs: Parquet partitioned by run, committed by overwriting a run's own partition."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def exists(self) -> bool:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/data")
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(p)

    def load(self) -> DataFrame | None:
        return self.spark.read.parquet(f"{self.path}/data") if self.exists() else None

    def append(self, accepted: DataFrame, run_id: str) -> None:
        """Idempotent: a run's replay overwrites what it wrote before."""
        accepted.select("id", "embedding").write.mode("overwrite").parquet(f"{self.path}/data/run_id={run_id}")

    def reset(self) -> None:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)


def dedup_embedding(df: DataFrame, threshold: float = 0.92, store: IndexStore | None = None, run_id: str | None = None, index: str = "auto", reset: bool = False) -> DataFrame:
    """df: records with an embedding column. Marks rows similar to an earlier run's, then to a kept row of this run (id order).
    The accepted vectors are appended to the store under run_id."""
    if store and reset:
        store.reset()
    new = materialize(undecided(df).where("embedding is not null").select("id", "embedding"), "vectors")
    old = store.load() if store else None
    pairs = materialize(vector_pairs(new, old, threshold, index), "cosines")
    seen = pairs.where("old").groupBy(F.col("b").alias("id")).agg(F.min("a").alias("_seen"))
    fresh = pairs.where("not old").select("a", "b").join(seen.select(F.col("id").alias("a")), "a", "left_anti").join(seen.select(F.col("id").alias("b")), "b", "left_anti")
    gone = first_independent_set(fresh).where("not kept").select(F.col("node").alias("id"), F.col("by").alias("_by"))
    df = df.join(materialize(seen, "seen"), "id", "left").join(materialize(gone, "gone"), "id", "left")
    df = reject(df, F.col("_seen").isNotNull(), "seen_in_earlier_run", "dedup_embedding", F.col("_seen"))
    df = reject(df, F.col("_by").isNotNull(), "embedding_duplicate", "dedup_embedding", F.col("_by")).drop("_seen", "_by")
    if store:
        df = materialize(df, "deduped")
        store.append(undecided(df), run_id or uuid.uuid4().hex)
    return df


def dedup_stats(df: DataFrame) -> DataFrame:
    """code, removed, survivors (distinct records that stayed for them), largest group removed."""
    gone = df.where("status = 'rejected' and rejection_reason rlike '_duplicate:'").select(F.substring_index("rejection_reason", ":", 1).alias("code"), F.substring_index("rejection_reason", ":", -1).alias("by"))
    return gone.groupBy("code", "by").agg(F.count(F.lit(1)).alias("n")).groupBy("code").agg(F.sum("n").alias("removed"), F.count(F.lit(1)).alias("survivors"), F.max("n").alias("largest"))


def match_near(left: DataFrame, right: DataFrame, n: int = 8, threshold: float = 0.5, broadcast_rows: int = 100_000) -> DataFrame:
    """Across collections: left id, right id, and the share of the right text's word n-grams that the left text holds.

    Grams of the right side are few; they are broadcast below a counted bound, else joined by shuffle."""
    grams = lambda df, name: df.select(F.col("id").alias(name), F.explode(F.array_distinct(tx.word_ngrams(F.col("text"), n))).alias("gram"))
    r = materialize(grams(right, "right_id"), "grams")
    sizes = r.groupBy("right_id").agg(F.count(F.lit(1)).alias("size"))
    few = r.count() <= broadcast_rows
    shared = grams(left, "left_id").join(F.broadcast(r) if few else r, "gram").groupBy("left_id", "right_id").agg(F.count(F.lit(1)).alias("shared"))
    return shared.join(F.broadcast(sizes) if few else sizes, "right_id").select("left_id", "right_id", (F.col("shared") / F.col("size")).alias("coverage")).where(F.col("coverage") >= threshold)
