"""Benchmark decontamination with SimHash windows, in DataFrame expressions.

A window is a run of as many words as a benchmark item has (a shorter text is one window), at every place of a text. A window with n
shingles is at the threshold t with an item of n only if t * 2n / (1 + t) of its shingles at least are some item's. So places of
shared shingles are counted along the text, and every window that holds enough of them is fingerprinted, whatever it lines up
with; the others cannot pass, so the reduction is exact. A window's SimHash is the sign of the summed +1/-1 bits of
its words' hashes, summed in lanes of 16 bits. Fingerprints are cut into RADIUS + 1 blocks; two within RADIUS bits agree on at least one block, so the
join on (item size, block, bits) finds all of them. No radius short of all bits is safe: an end rewritten to similarity 0.8 moves 15 bits
or more in some windows, and more where words repeat. So a window that holds one of the item's rarest shingles is a candidate
whatever its fingerprint. A window at the threshold lacks at most 1 - threshold of the item's shingles, so of one more than that
(repeats counted) it holds at least one, and no pair is lost. The candidates' exact similarity then decides: the sum of the lesser
over the sum of the greater multiplicity of each five-word shingle. Items with equal words are compared once.

The benchmark side is broadcast only below a counted bound, else joined by shuffle. Documents with hits grow with the table, so they meet the
texts in a merge join at every size, which shuffles the texts once; on tables above Spark's own threshold its runtime Bloom filter keeps
texts without hits out of that shuffle.

Defined results: null or empty texts and items match nothing. Items of fewer than five words are one shingle, and match texts' windows
of their own size. Repeated documents and items are judged each; among equal similarities the least item_id is named. Empty
tables: every document is clean. Documents' other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from refinery.llm.common import MIN_SIMILARITY, SHINGLE_WORDS, let, stage, words_col

#: Greatest Hamming distance of fingerprints; bits in a block of RADIUS + 1; anchors that may be broadcast (16 bytes each).
RADIUS, BITS, BROADCAST_ROWS = 15, 64, 500_000


def shingles(words: Column, width: int) -> Column:
    """64-bit hashes of the windows of `width` words, in order; none for a shorter text."""
    of = lambda w: F.transform(F.sequence(F.lit(1), F.size(w) - (width - 1)), lambda i: F.xxhash64(F.slice(w, i, width)))
    return let(words, lambda w: F.when(F.size(w) >= width, of(w)).otherwise(F.array().cast("array<bigint>")))


def simhash(words: Column) -> Column:
    return let(F.transform(words, lambda w: F.xxhash64(w)), _signs)


def _signs(hashes: Column) -> Column:
    """Bit b is set if more than half of the hashes have it. Four bits are counted at once, in lanes of 16 bits (windows of up to 65,535
    words; of more, the lanes carry over, which only costs candidates by fingerprint)."""
    lanes = F.lit(0x0001000100010001).cast("long")
    lane_of = lambda k: lambda a, h: a + F.call_function("shiftrightunsigned", h, F.lit(k)).bitwiseAND(lanes)
    sums = [F.aggregate(hashes, F.lit(0).cast("long"), lane_of(k)) for k in range(16)]
    half = F.size(hashes) / 2

    def gathered(sums: Column) -> Column:
        out = F.lit(0).cast("long")
        for b in range(BITS):
            n = F.call_function("shiftrightunsigned", F.get(sums, F.lit(b % 16)), F.lit(b - b % 16)).bitwiseAND(F.lit(0xFFFF).cast("long"))
            out = out.bitwiseOR(F.when(n > half, F.call_function("shiftleft", F.lit(1).cast("long"), F.lit(b))).otherwise(F.lit(0).cast("long")))
        return out

    return let(F.array(*sums), gathered)


def blocks(print_: Column, radius: int = RADIUS) -> Column:
    """radius + 1 (block number, bits) pairs that cover the fingerprint."""
    n = radius + 1
    edges = [BITS * k // n for k in range(n + 1)]
    return F.array(*[F.struct(F.lit(k).alias("k"), F.call_function("shiftrightunsigned", print_, F.lit(lo)).bitwiseAND(F.lit((1 << (hi - lo)) - 1).cast("long")).alias("bits")) for k, (lo, hi) in enumerate(zip(edges, edges[1:]))])


def weighted_similarity(a: Column, b: Column) -> Column:
    """Lesser over greater multiplicities, summed over the shingles of two arrays."""
    return let(a, lambda x: let(b, lambda y: _weighted(x, y)))


def _weighted(a: Column, b: Column) -> Column:
    count = lambda xs, x: F.size(F.filter(xs, lambda y: y == x))
    once = lambda xs: F.size(F.array_distinct(xs)) == F.size(xs)
    counted = F.aggregate(F.array_intersect(a, b), F.lit(0), lambda s, x: s + F.least(count(a, x), count(b, x)))
    both = F.when(once(a) | once(b), F.size(F.array_intersect(a, b))).otherwise(counted)
    return both / (F.size(a) + F.size(b) - both)


def _items(benchmark: DataFrame, width: int) -> DataFrame:
    """An item for each distinct run of words: its least id, and how many ids have it."""
    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), words_col(F.col("text")).alias("item_words"))
    rows = rows.groupBy("item_words").agg(F.min("item_id").alias("item_id"), F.countDistinct("item_id").alias("n_ids"))
    rows = rows.withColumn("item_size", F.size("item_words")).where("item_size > 0").withColumn("gram", F.least(F.col("item_size"), F.lit(width)))
    grams = F.lit(None)
    for g in range(1, width + 1):
        grams = F.when(F.col("gram") == g, shingles(F.col("item_words"), g)).otherwise(grams)
    return rows.withColumn("item_shingles", grams).withColumn("item_print", simhash(F.col("item_words")))


def rare_shingles(items: DataFrame, threshold: float) -> DataFrame:
    """item_id, item_size, shingle: of each item, the shingles in fewest items, one more than a window at the threshold may lack."""
    own = items.select("item_id", "item_size", F.xxhash64("item_words").alias("item_mark"), "item_shingles").distinct()
    rows = own.select("item_id", "item_size", "item_mark", F.size("item_shingles").alias("n"), F.explode("item_shingles").alias("shingle"))
    held_by = rows.groupBy("shingle").agg(F.count(F.lit(1)).alias("held_by"))
    order = Window.partitionBy("item_id", "item_mark").orderBy("held_by", "shingle")
    ranked = rows.join(held_by, "shingle").withColumn("rank", F.row_number().over(order))
    return ranked.where(F.col("rank") <= F.floor(F.col("n") * (1 - threshold) + 1e-9) + 1).select("item_id", "item_size", "shingle").distinct()


def enough(threshold: float) -> Column:
    """The starts of the windows that hold enough of the shared shingles' places to reach the threshold, each once: with the k-th place
    as its first, a window starts after the one before, and late enough to hold the last place that it needs."""
    item, window = F.col("item_size") - F.col("gram") + 1, F.least("n_words", "item_size") - F.col("gram") + 1
    need = F.greatest(F.ceil((item + window) * (threshold / (1 + threshold)) - 1e-9), F.lit(1)).cast("int")
    most, m = F.greatest(F.col("n_words") - F.col("item_size"), F.lit(0)), F.size("places")

    def starts(k: Column) -> Column:
        low = F.greatest(F.coalesce(F.get(F.col("places"), k - 1) + 1, F.lit(0)), F.get(F.col("places"), k + need - 1) - (window - 1), F.lit(0))
        high = F.least(F.get(F.col("places"), k), most)
        return F.when(low <= high, F.sequence(low, high)).otherwise(F.array().cast("array<int>"))

    return F.when(m >= need, F.flatten(F.transform(F.sequence(F.lit(0), m - need), starts))).otherwise(F.array().cast("array<int>"))


def contaminated(docs: DataFrame, benchmark: DataFrame, threshold: float = MIN_SIMILARITY, width: int = SHINGLE_WORDS, radius: int = RADIUS) -> DataFrame:
    """One row per row of docs (doc_id, text): doc_id, contaminated, item_id, similarity, start (word number of the window from 0), n_items."""
    items = stage(_items(benchmark, width), "items")
    anchors = items.select("gram", "item_size", F.posexplode("item_shingles").alias("at", "shingle")).distinct()
    n_anchors = anchors.count()
    small = lambda df, factor=1: F.broadcast(df) if n_anchors * factor <= BROADCAST_ROWS else df
    widths = sorted(r[0] for r in items.select("gram").distinct().collect())  # at most `width` numbers
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    mark = F.xxhash64("text")
    hits = None
    for g in widths:
        of_width = lambda w: F.struct(F.size(w).alias("n_words"), shingles(w, g).alias("grams"))  # noqa: B023, E731  used at once
        found = rows.select("doc_id", mark.alias("mark"), F.inline(F.transform(F.array(words_col(F.col("text"))), of_width))).where(F.size("grams") > 0).select("doc_id", "mark", "n_words", F.posexplode("grams").alias("pos", "shingle"))
        found = found.join(small(anchors.where(F.col("gram") == g).select("item_size", "shingle").distinct()), "shingle").select("doc_id", "mark", "n_words", "item_size", F.lit(g).alias("gram"), "pos")
        hits = found if hits is None else hits.unionByName(found)
    if hits is None:
        return rows.select("doc_id", F.lit(False).alias("contaminated"), F.lit(None).cast("long").alias("item_id"), F.lit(None).cast("double").alias("similarity"), F.lit(None).cast("int").alias("start"), F.lit(0).cast("long").alias("n_items"))
    # the places of one row stay together as an array: rows with hits are few, and each has one place per word and item size at most
    hits = stage(hits, "hits")
    at = hits.groupBy("doc_id", "mark", "n_words", "item_size", "gram").agg(F.array_sort(F.collect_set("pos")).alias("places"))
    at = at.withColumn("starts", enough(threshold)).where(F.size("starts") > 0)
    at = at.groupBy("doc_id", "mark").agg(F.flatten(F.collect_list(F.transform("starts", lambda s: F.struct(F.col("item_size"), s.alias("start"))))).alias("places"))
    texts = rows.withColumn("mark", mark).alias("r").join(at.hint("merge").alias("h"), F.col("r.doc_id").eqNullSafe(F.col("h.doc_id")) & (F.col("r.mark") == F.col("h.mark")))
    # windows leave a row one by one, without the row's words; equal windows of a row count once, at their first place
    cut = lambda w: F.transform("places", lambda p: F.struct(p["item_size"].alias("item_size"), p["start"].alias("start"), F.slice(w, p["start"] + 1, p["item_size"]).alias("window")))
    windows = texts.select("r.doc_id", "r.mark", F.inline(let(words_col(F.col("text")), cut)).alias("item_size", "start", "window"))
    windows = windows.groupBy("doc_id", "mark", "item_size", "window").agg(F.min("start").alias("start"))
    windows = stage(windows.withColumn("print", simhash(F.col("window"))), "windows")
    left = windows.select("doc_id", "mark", "item_size", "start", "print", F.inline(blocks(F.col("print"), radius)).alias("k", "bits"))
    right = items.select("item_id", "item_size", "item_print", F.inline(blocks(F.col("item_print"), radius)).alias("k", "bits"))
    pairs = left.join(small(right, radius + 1), ["item_size", "k", "bits"]).where(F.bit_count(F.col("print").bitwiseXOR(F.col("item_print"))) <= radius)
    # the fingerprints decide the pairs; the first agreeing block names each pair once
    first = F.array_min(F.filter(F.sequence(F.lit(0), F.lit(radius)), lambda b: F.element_at(blocks(F.col("print"), radius), b + 1) == F.element_at(blocks(F.col("item_print"), radius), b + 1)))
    pairs = pairs.where(F.col("k") == first).select("doc_id", "mark", "item_size", "start", "item_id")
    grams = F.lit(None)
    for g in widths:
        grams = F.when(F.least(F.col("item_size"), F.lit(width)) == g, shingles(F.col("window"), g)).otherwise(grams)
    held = windows.select("doc_id", "mark", "item_size", "start", F.explode(F.array_distinct(grams)).alias("shingle"))
    held = held.join(small(stage(rare_shingles(items, threshold), "rare")), ["item_size", "shingle"]).select("doc_id", "mark", "item_size", "start", "item_id")
    pairs = pairs.unionByName(held).distinct()
    pairs = pairs.alias("p").join(small(items.select("item_id", F.col("item_size").alias("size_"), "gram", "item_shingles", "n_ids"), 40).alias("i"), (F.col("p.item_id").eqNullSafe(F.col("i.item_id"))) & (F.col("p.item_size") == F.col("i.size_")))
    pairs = pairs.select("p.doc_id", "p.mark", "p.item_size", "p.start", "p.item_id", "gram", "item_shingles", "n_ids")
    full = pairs.alias("p").join(windows.alias("w"), F.col("p.doc_id").eqNullSafe(F.col("w.doc_id")) & (F.col("p.mark") == F.col("w.mark")) & (F.col("p.item_size") == F.col("w.item_size")) & (F.col("p.start") == F.col("w.start")))
    grams = F.lit(None)
    for g in widths:
        grams = F.when(F.col("gram") == g, shingles(F.col("window"), g)).otherwise(grams)
    full = full.select("p.doc_id", "p.mark", "p.item_id", "n_ids", "p.start", weighted_similarity(F.col("item_shingles"), grams).alias("similarity")).where(F.col("similarity") >= threshold)
    full = full.groupBy("doc_id", "mark", "item_id").agg(F.min(F.struct(-F.col("similarity"), F.col("start"))).alias("first"), F.max("n_ids").alias("n_ids"))
    full = full.select("doc_id", "mark", F.struct(F.col("first.col1").alias("far"), "item_id", F.col("first.start").alias("start")).alias("place"), "n_ids")
    best = full.groupBy("doc_id", "mark").agg(F.min("place").alias("place"), F.sum("n_ids").alias("n_items"))
    best = best.select("doc_id", "mark", F.struct(F.col("place.item_id").alias("item_id"), (-F.col("place.far")).alias("similarity"), F.col("place.start").alias("start")).alias("best"), "n_items")
    best = stage(best, "leaks")
    out = rows.select("doc_id", mark.alias("mark")).alias("r").join(best.alias("b"), F.col("r.doc_id").eqNullSafe(F.col("b.doc_id")) & (F.col("r.mark") == F.col("b.mark")), "left")
    return out.select("r.doc_id", F.col("best").isNotNull().alias("contaminated"), F.col("best.item_id").alias("item_id"), F.col("best.similarity").alias("similarity"), F.col("best.start").alias("start"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"))


def drop_leaks(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows of docs that hold no benchmark item, with their columns."""
    leaks = contaminated(docs, benchmark, **options).where("contaminated").select(F.col("doc_id").alias("leak_id")).distinct()
    return docs.join(leaks, F.col("doc_id").eqNullSafe(F.col("leak_id")), "left_anti")


ORACLE = r"""
with b0 as (select item_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') as ws from benchmark),
b as (select item_id, len(ws) - 4 as n, list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i : i + 4], ' ')) as sh from b0 where len(ws) >= 5),
d0 as (select row_number() over () as r, doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') as ws from documents),
d as (select r, list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i : i + 4], ' ')) as sh from d0 where len(ws) >= 5),
p as (select distinct r, item_id from (select r, unnest(sh) as s from d) join (select item_id, unnest(sh) as s from b) using (s)),
w as (select r, item_id, unnest(range(0, greatest(len(d.sh) - n, 0) + 1)) as start from p join d using (r) join b using (item_id)),
x as (select r, item_id, start, d.sh[start + 1 : start + n] as ws, b.sh as bs from w join d using (r) join b using (item_id)),
m as (select r, item_id, start, len(ws) as nx, len(bs) as nb, case when len(list_filter(ws, lambda s: list_contains(bs, s))) = 0 then 0 else
  list_sum(list_transform(list_distinct(list_intersect(ws, bs)), lambda s: least(len(list_filter(ws, lambda y: y = s)), len(list_filter(bs, lambda y: y = s))))) end as both_ from x),
s as (select r, item_id, start, both_ / (nx + nb - both_)::double as similarity from m where both_ / (nx + nb - both_)::double >= 0.8),
g as (select r, count(distinct item_id) as n_items, min((-similarity, item_id, start)) as best from s group by r)
select doc_id, best is not null as contaminated, coalesce(best[2], -1) as item_id, coalesce(-best[1], 0) as similarity, coalesce(best[3], -1)::int as start, coalesce(n_items, 0)::bigint as n_items from d0 left join g using (r)
"""
