"""Mixing sources to target weights along a curriculum, in DataFrame expressions.

Each source gets a target (its share of the budget, stopped at `most` passes over the source, the excess reshared by
weight). Within a source, documents lie one after another in hash order; pass e puts a document at offsets
e * source_size + start. A source's weight changes over training as a line between knots; its integral, scaled to the
target, is the demand for the source's words up to time t. A copy is trained at the time when the demand reaches its
middle, so inverting the demand gives its position. The last copy of a source is taken as far as the target reaches.

Prefix sums are taken in two steps, over hash cells of a source and then inside a cell, so a source with most rows
is spread over as many tasks as it needs.

Defined results: a null text has size 0; size-0 documents are never taken. Null sources come last and form one source. A source
without words has target 0 and gives nothing; its weight stays with the others. Repeated rows count each, also where they share a doc_id
but not the text. An empty table gives an empty result. Other columns are ignored by `schedule`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from refinery.llm.common import stage, words_col

#: Weights in turn over the sources, budget as a share of all words, most passes over a source.
WEIGHTS, BUDGET, MOST = (3.0, 1.0, 2.0), 1.5, 2.0
#: Weight over training time for each slot of WEIGHTS, as (time, weight) knots: falling, level, rising.
SHAPES = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (0.5, 1.0), (1.0, 1.5)))
SEED = "mix-1"
CELLS = 4096


def size_of(text: Column) -> Column:
    """Number of words, without building them: blanks runs removed from the ends, then counted."""
    return F.size(words_col(text)).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, most: float = MOST) -> DataFrame:
    """sizes: source, source_size (one row a source, so far fewer than documents). Adds slot, weight and target.

    Sources stop at their cap in the order of cap / weight; the level is what is left over the weights still open.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    slot = F.pmod(F.row_number().over(order) - 1, F.lit(len(weights)))
    rows = sizes.withColumn("slot", slot).withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), F.col("slot") + 1))
    by_ratio = Window.orderBy((F.col("source_size") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before, onward = by_ratio.rowsBetween(Window.unboundedPreceding, -1), by_ratio.rowsBetween(0, Window.unboundedFollowing)
    everyone = Window.partitionBy(F.lit(1))
    rows = rows.withColumns({"full_before": F.coalesce(F.sum(F.col("source_size") * most).over(before), F.lit(0.0)), "open_weight": F.sum("weight").over(onward), "total": F.sum("source_size").over(everyone) * budget})
    level = (F.col("total") - F.col("full_before")) / F.col("open_weight")
    rows = rows.withColumn("level", level).withColumn("stopped", F.col("source_size") * most <= F.col("weight") * F.col("level"))
    rows = rows.withColumn("shared", F.max(F.when(~F.col("stopped"), F.col("level"))).over(everyone))
    target = F.when(F.col("stopped"), F.col("source_size") * most).otherwise(F.col("weight") * F.col("shared"))
    return rows.select("source", "source_size", "slot", target.cast("double").alias("target"))


def time_at(share: Column, knots) -> Column:
    """The time by which `share` (0 to 1) of a source's demand is met: the inverse of the integral of its weight."""
    areas = [(t1 - t0) * (w0 + w1) / 2 for (t0, w0), (t1, w1) in zip(knots, knots[1:])]
    total, done, out = sum(areas), 0.0, F.lit(float(knots[-1][0]))
    pieces = []
    for ((t0, w0), (t1, w1)), area in zip(zip(knots, knots[1:]), areas):
        rest, slope = share * total - F.lit(done), (w1 - w0) / (t1 - t0)
        root = F.sqrt(F.greatest(F.lit(w0 * w0) + rest * (2 * slope), F.lit(0.0)))
        pieces.append((done + area, F.lit(t0) + rest * 2 / (F.lit(w0) + root)))
        done += area
    for upto, at in reversed(pieces):
        out = F.when(share * total <= upto, at).otherwise(out)
    return F.least(F.greatest(out, F.lit(float(knots[0][0]))), F.lit(float(knots[-1][0])))


def schedule(docs: DataFrame, weights=WEIGHTS, shapes=SHAPES, budget: float = BUDGET, most: float = MOST, seed: str = SEED) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, taken, and copies, an array of
    struct(pass, words, position); position lies between 0 and 1."""
    rows = stage(_dealt(docs.select("doc_id", "source", size_of(F.col("text")).alias("size")), seed), "mix-sizes")
    return _scheduled(rows, [], weights, shapes, budget, most)


def _dealt(rows: DataFrame, seed: str) -> DataFrame:
    """Adds rank, the hash order of a source's rows, and its cell."""
    rank = F.md5(F.concat(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    return rows.withColumn("rank", rank).withColumn("cell", F.conv(F.substring("rank", 1, 3), 16, 10).cast("int"))


def _scheduled(rows: DataFrame, more: list[str], weights, shapes, budget: float, most: float) -> DataFrame:
    """rows: doc_id, source, size, rank, cell and the columns `more`, which pass through; the first of them orders rows of one doc_id and size."""
    cells = stage(rows.groupBy("source", "cell").agg(F.sum("size").alias("cell_size")), "mix-cells")
    of_source = targets(cells.groupBy("source").agg(F.sum("cell_size").alias("source_size")), weights, budget, most)
    by_cell = Window.partitionBy("source").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    cells = cells.withColumn("cell_start", F.coalesce(F.sum("cell_size").over(by_cell), F.lit(0)))
    cells = cells.alias("c").join(of_source.alias("s"), F.col("c.source").eqNullSafe(F.col("s.source"))).select("c.source", "cell", "cell_start", "source_size", "slot", "target")
    inside = Window.partitionBy("source", "cell").orderBy("rank", "doc_id", "size", *more[:1]).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("in_cell", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    rows = rows.alias("r").join(cells.alias("c"), F.col("r.source").eqNullSafe(F.col("c.source")) & (F.col("r.cell") == F.col("c.cell")))
    rows = rows.select("doc_id", "r.source", *more, "size", "source_size", "slot", "target", (F.col("cell_start") + F.col("in_cell")).alias("start"))
    passes = int(most) + (most > int(most))
    copies = []
    for e in range(passes):
        at = F.col("start") + F.col("source_size") * e
        words = F.least(F.greatest(F.floor(F.col("target")) - at, F.lit(0)), F.col("size")).cast("long")
        share = F.try_divide(at + words / 2, F.col("target"))
        when = F.lit(None).cast("double")
        for k, knots in enumerate(shapes):
            when = F.when(F.col("slot") == k, time_at(share, knots)).otherwise(when)
        copies.append(F.struct(F.lit(e).alias("pass"), words.alias("words"), when.alias("position")))
    rows = rows.withColumn("copies", F.filter(F.array(*copies), lambda c: c["words"] > 0))
    taken = F.aggregate("copies", F.lit(0).cast("long"), lambda a, c: a + c["words"])
    return rows.select("doc_id", "source", *more, "size", "source_size", "target", taken.alias("taken"), "copies")


def range_sorted(rows: DataFrame, position: str) -> DataFrame:
    """Global order by training position as ranges: file k holds earlier positions than file k + 1."""
    return rows.repartitionByRange(F.col(position), F.col("doc_id")).sortWithinPartitions(position, "doc_id")


def training_order(docs: DataFrame, weights=WEIGHTS, shapes=SHAPES, budget: float = BUDGET, most: float = MOST, seed: str = SEED) -> DataFrame:
    """The documents in training order: one row for each copy that the mix takes, with the columns of `docs` and
    mix_pass, mix_words, mix_position (named so that they clash with no column of documents). Rows carry their columns through the
    prefix sums, so rows that share a doc_id keep words and positions of their own."""
    rows = docs.select("doc_id", "source", size_of(F.col("text")).alias("size"), F.xxhash64("source", "text").alias("mark"), F.struct("*").alias("row"))
    plan = _scheduled(_dealt(rows, seed), ["mark", "row"], weights, shapes, budget, most).select("row", F.explode("copies").alias("c"))
    out = plan.select("row.*", F.col("c.pass").alias("mix_pass"), F.col("c.words").alias("mix_words"), F.col("c.position").alias("mix_position"))
    return range_sorted(out, "mix_position")


ORACLE = r"""
with d as (select doc_id, source, cast(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as bigint) as size, md5('mix-1' || coalesce(cast(doc_id as varchar), '')) as rank from documents),
s as (select source, sum(size)::bigint as source_size from d group by source),
w as (select source, source_size, [3.0, 1.0, 2.0][(row_number() over (order by source asc nulls last) - 1) % 3 + 1]::double as weight from s),
o as (select *, coalesce(sum(source_size * 2.0::double) over (order by source_size / weight, source nulls last rows between unbounded preceding and 1 preceding), 0.0::double) as before,
  sum(weight) over (order by source_size / weight, source nulls last rows between current row and unbounded following) as open_weight,
  sum(source_size) over () * 1.5::double as total from w),
l as (select *, (total - before) / open_weight as level from o),
f as (select *, source_size * 2.0::double <= weight * level as stopped from l),
t as (select source, source_size, case when stopped then source_size * 2.0::double else weight * max(case when not stopped then level end) over () end as target from f),
p as (select d.doc_id, d.size, t.source_size, t.target, coalesce(sum(d.size) over (partition by d.source order by d.rank, d.doc_id, d.size rows between unbounded preceding and 1 preceding), 0) as start
  from d join t on d.source is not distinct from t.source)
select doc_id, size, source_size, target, cast(least(greatest(floor(target) - start, 0), size) + least(greatest(floor(target) - start - source_size, 0), size) as bigint) as taken from p
"""
