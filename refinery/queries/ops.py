"""The relational and streaming surface around the methods."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from refinery.operators.storage import shared_dir
from refinery.queries.base import query, read
from refinery.streaming import incremental


@query("select n_name, count(*)::bigint as n, round(sum(c_acctbal), 2) as balance from customer join nation on c_nationkey = n_nationkey group by n_name")
def ops_join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation = read(spark, sf_dir, "nation")  # a fixed table of 25 rows
    rows = read(spark, sf_dir, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query("select o_orderpriority, count(*)::bigint as lines, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from orders join lineitem on l_orderkey = o_orderkey where l_quantity > 25 group by o_orderpriority")
def ops_join_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read(spark, sf_dir, "lineitem").where("l_quantity > 25").select("l_orderkey", "l_extendedprice", "l_discount")
    rows = lines.join(read(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("select c_custkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > 300000)")
def ops_join_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    big = read(spark, sf_dir, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("c_custkey"))
    return read(spark, sf_dir, "customer").select("c_custkey").join(big, "c_custkey", "left_semi")


@query("select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)")
def ops_join_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "customer").select("c_custkey").join(read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@query("""select d.doc_id, coalesce(l.quality, -1) as quality, coalesce(l.toxic, -1) as toxic from documents d left join labels l using (doc_id)""")
def ops_join_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "documents").select("doc_id").join(read(spark, sf_dir, "labels"), "doc_id", "left")
    return rows.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.coalesce("toxic", F.lit(-1)).alias("toxic"))


@query("""with b as (select p_brand as brand, min(p_retailprice) as lo, max(p_retailprice) as hi from part group by p_brand)
select brand, count(*)::bigint as n from b join part p on p.p_retailprice between b.lo and b.lo + 50 group by brand""")
def ops_join_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range join by cells of the range's width: each interval meets the one or two cells it touches, then the exact condition."""
    width = 50
    part = read(spark, sf_dir, "part").select("p_brand", "p_retailprice")
    lo = part.groupBy(F.col("p_brand").alias("brand")).agg(F.min("p_retailprice").alias("lo"))
    lo = lo.withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("lo") + width) / width))))
    rows = part.withColumn("cell", F.floor(F.col("p_retailprice") / width)).join(lo, "cell").where(F.col("p_retailprice").between(F.col("lo"), F.col("lo") + width))
    return rows.groupBy("brand").agg(F.count(F.lit(1)).alias("n"))


@query("""with p as (select event_id, user_id, ts from events where event_type = (select min(event_type) from events)),
a as (select user_id, ts, event_id as earlier, value from events where event_type = (select max(event_type) from events))
select p.event_id, coalesce(a.earlier, -1) as earlier from p left join lateral (select earlier from a where a.user_id = p.user_id and a.ts <= p.ts order by a.ts desc, a.earlier desc limit 1) a on true""")
def ops_join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The latest event of one type at or before each event of another, per user: one union, one window, no join."""
    events = read(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    ends = events.agg(F.min("event_type").alias("lo"), F.max("event_type").alias("hi"))
    rows = events.join(F.broadcast(ends), (F.col("event_type") == F.col("lo")) | (F.col("event_type") == F.col("hi")))
    rows = rows.withColumn("probe", F.col("event_type") == F.col("lo"))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("probe").cast("int"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(~F.col("probe"), F.col("event_id")), ignorenulls=True).over(w)
    return rows.withColumn("earlier", last).where("probe").select("event_id", F.coalesce("earlier", F.lit(-1)).alias("earlier"))


@query("select coalesce(l_returnflag, 'all') as flag, coalesce(l_linestatus, 'all') as status, count(*)::bigint as n, sum(l_quantity)::double as quantity from lineitem group by rollup (l_returnflag, l_linestatus)")
def ops_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))
    return rows.select(F.coalesce("l_returnflag", F.lit("all")).alias("flag"), F.coalesce("l_linestatus", F.lit("all")).alias("status"), "n", "quantity")


@query("select coalesce(lang, 'all') as lang, coalesce(source, 'all') as source, count(*)::bigint as n, sum(n_chars)::bigint as chars from documents group by cube (lang, source)")
def ops_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))
    return rows.select(F.coalesce("lang", F.lit("all")).alias("lang"), F.coalesce("source", F.lit("all")).alias("source"), "n", "chars")


@query("select coalesce(o_orderstatus, '-') as status, coalesce(o_orderpriority, '-') as priority, count(*)::bigint as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def ops_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read(spark, sf_dir, "orders")
    return spark.sql("select coalesce(o_orderstatus, '-') as status, coalesce(o_orderpriority, '-') as priority, count(*) as n from {o} group by grouping sets ((o_orderstatus), (o_orderpriority), ())", o=orders)


@query("""select lang, count(*) filter (where toxic = 0)::bigint as clean, count(*) filter (where toxic = 1)::bigint as toxic from documents join labels using (doc_id) group by lang""")
def ops_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "documents").select("doc_id", "lang").join(read(spark, sf_dir, "labels"), "doc_id")
    return rows.groupBy("lang").pivot("toxic", [0, 1]).count().select("lang", F.coalesce("0", F.lit(0)).alias("clean"), F.coalesce("1", F.lit(0)).alias("toxic"))


@query("""select o_orderkey, row_number() over w as rn, rank() over (partition by o_custkey order by o_orderdate) as rnk, dense_rank() over (partition by o_custkey order by o_orderdate) as dense,
  coalesce(lag(o_orderkey) over w, -1) as before, coalesce(lead(o_orderkey) over w, -1) as after, ntile(4) over w as quarter, round(sum(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row), 2) as running
from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)""")
def ops_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    by_date = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_totalprice")
    return orders.select(
        "o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(by_date).alias("rnk"), F.dense_rank().over(by_date).alias("dense"), F.coalesce(F.lag("o_orderkey").over(w), F.lit(-1)).alias("before"), F.coalesce(F.lead("o_orderkey").over(w), F.lit(-1)).alias("after"),
        F.ntile(4).over(w).alias("quarter"), F.round(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"),
    )


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25")
def ops_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("select source, doc_id, n_chars from (select source, doc_id, n_chars, row_number() over (partition by source order by n_chars desc, doc_id) as r from documents) where r <= 3")
def ops_top_k_by_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The top of each group without a window over it: partial tops merge as the groups' aggregates."""
    docs = read(spark, sf_dir, "documents").select("source", "doc_id", "n_chars")
    salted = docs.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(64)))
    part = Window.partitionBy("source", "salt").orderBy(F.desc("n_chars"), "doc_id")
    whole = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    few = salted.withColumn("r", F.row_number().over(part)).where("r <= 3").drop("r", "salt")
    return few.withColumn("r", F.row_number().over(whole)).where("r <= 3").drop("r")


@query("select c_nationkey as k from customer intersect select s_nationkey from supplier")
def ops_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).intersect(read(spark, sf_dir, "supplier").select("s_nationkey"))


@query("select p_partkey as k from part except all select l_partkey from lineitem")
def ops_except_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "part").select(F.col("p_partkey").alias("k")).exceptAll(read(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("k")))


@query("select 'c' as kind, c_custkey as k, c_acctbal as balance, null as brand from customer union all select 'p', p_partkey, null, p_brand from part")
def ops_union_by_name(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read(spark, sf_dir, "customer").select(F.lit("c").alias("kind"), F.col("c_custkey").alias("k"), F.col("c_acctbal").alias("balance"))
    p = read(spark, sf_dir, "part").select(F.lit("p").alias("kind"), F.col("p_partkey").alias("k"), F.col("p_brand").alias("brand"))
    return c.unionByName(p, allowMissingColumns=True)


@query("select event_id, json_extract_string(props, '$.' || (json_keys(props))[1]) as first_value, len(json_keys(props))::int as n_keys from events")
def ops_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    keys = F.json_object_keys("props")
    return read(spark, sf_dir, "events").select("event_id", F.element_at(F.from_json("props", "map<string,string>"), F.element_at(keys, 1)).alias("first_value"), F.size(keys).alias("n_keys"))


@query("select date_trunc('hour', ts) as start, event_type, count(*)::bigint as n from events group by all")
def ops_window_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return incremental.windowed_counts(read(spark, sf_dir, "events"), "1 hour").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("""select date_trunc('hour', ts) - to_hours(k) as start, event_type, count(*)::bigint as n from events, (values (0), (1)) as s(k) group by all""")
def ops_window_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return incremental.windowed_counts(read(spark, sf_dir, "events"), "2 hours", slide="1 hour").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("""with e as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 30 minute or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events),
s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from e)
select user_id, min(ts) as start, max(ts) + interval 30 minute as "end", count(*)::bigint as n from s group by user_id, k""")
def ops_window_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = incremental.sessions(read(spark, sf_dir, "events"))
    return rows.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


@query("""select event_type, round(quantile_cont(value, 0.5), 4) as median, count(distinct user_id)::bigint as users, max_by(event_id, (value, event_id)) as top_event from events group by event_type""")
def ops_aggregates(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "events").groupBy("event_type")
    return rows.agg(F.round(F.percentile("value", 0.5), 4).alias("median"), F.countDistinct("user_id").alias("users"), F.max_by("event_id", F.struct("value", "event_id")).alias("top_event"))


@query()
def ops_sketches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Approximate counts and quantiles for run cards: mergeable sketches, one small row a group."""
    rows = read(spark, sf_dir, "documents").groupBy("source")
    return rows.agg(F.approx_count_distinct("text", 0.02).alias("about_distinct"), F.percentile_approx("n_chars", [0.5, 0.99], 1000).alias("quantiles"), F.hll_sketch_estimate(F.hll_sketch_agg("text")).alias("hll"))


@query("""select doc_id, case when row_number() over (partition by key order by doc_id) = 1 then null when min(doc_id) over (partition by key) is not null then 'exact_duplicate' end as reason
from (select doc_id, sha256(trim(regexp_replace(lower(text), '\\s+', ' ', 'g'))) as key from documents)""")
def stream_incremental_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents as a stream of files, marked by micro-batch and read back from the batches' partitions."""
    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    path = f"{sf_dir}/documents.parquet"
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).parquet(f"{sf_dir}/documents*.parquet")
    incremental.run_incremental(stream.select("doc_id", "text"), root)
    return spark.read.parquet(f"{root}/rows").select("doc_id", "reason")


@query(r"""select p_partkey, upper(p_name) as shout, length(p_name)::int as n, replace(p_name, ' ', '_') as joined, substr(p_name, 2, 4) as part, lpad(p_partkey::varchar, 8, '0') as padded, position('a' in p_name)::int as first_a, reverse(p_name) as back, string_split(p_name, ' ')[1] as head,
  levenshtein(p_name, p_brand)::int as far, repeat(p_brand, 2) as twice, trim(p_brand || '  ') as trimmed, starts_with(p_brand, 'Brand') as branded, translate(p_name, 'aeiou', '12345') as coded from part""")
def ops_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    name, brand = F.col("p_name"), F.col("p_brand")
    return read(spark, sf_dir, "part").select(
        "p_partkey", F.upper(name).alias("shout"), F.length(name).alias("n"), F.replace(name, F.lit(" "), F.lit("_")).alias("joined"), F.substring(name, 2, 4).alias("part"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"), F.instr(name, "a").alias("first_a"), F.reverse(name).alias("back"),
        F.get(F.split(name, " "), F.lit(0)).alias("head"), F.levenshtein(name, brand).alias("far"), F.repeat(brand, 2).alias("twice"), F.trim(F.concat(brand, F.lit("  "))).alias("trimmed"), F.startswith(brand, F.lit("Brand")).alias("branded"), F.translate(name, "aeiou", "12345").alias("coded"),
    )


@query("""select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, day(o_orderdate)::int as d, quarter(o_orderdate)::int as q, dayofyear(o_orderdate)::int as doy, isodow(o_orderdate)::int as dow, strftime(o_orderdate, '%Y/%m') as label, date_diff('day', date '1992-01-01', o_orderdate::date)::int as days,
  last_day(o_orderdate::date)::varchar as month_end, (o_orderdate::date + interval 1 month)::date::varchar as next_month, date_trunc('month', o_orderdate)::date::varchar as month_start, epoch(o_orderdate)::bigint as seconds from orders""")
def ops_dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate").cast("date")
    return read(spark, sf_dir, "orders").select(
        "o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.dayofmonth(d).alias("d"), F.quarter(d).alias("q"), F.dayofyear(d).alias("doy"), (F.weekday(d) + 1).alias("dow"), F.date_format(d, "yyyy/MM").alias("label"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("days"), F.last_day(d).cast("string").alias("month_end"),
        F.add_months(d, 1).cast("string").alias("next_month"), F.trunc(d, "month").cast("string").alias("month_start"), F.unix_timestamp(F.col("o_orderdate").cast("timestamp")).alias("seconds"),
    )


@query("select doc_id, k::int as k, word from (select doc_id, unnest(range(0, len(w))) as k, unnest(w) as word from (select doc_id, list_filter(string_split_regex(text, '\\s+'), lambda x: x <> '')[1:5] as w from documents))")
def ops_table_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table function in a lateral join: the first five words of each text."""
    from refinery.functions import sql

    sql.register(spark)
    read(spark, sf_dir, "documents").createOrReplaceTempView("refinery_documents")
    return spark.sql("select doc_id, w.k, w.word from refinery_documents, lateral first_words(text, 5) w")


@query("""select doc_id, len(list_filter(string_split_regex(text, '\\s+'), lambda w: w <> ''))::bigint as n_tokens, sha256(trim(regexp_replace(lower(text), '\\s+', ' ', 'g'))) as key from documents""")
def ops_sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The engine's functions by name in SQL."""
    from refinery.functions import sql

    sql.register(spark)
    read(spark, sf_dir, "documents").createOrReplaceTempView("refinery_documents")
    return spark.sql("select doc_id, refinery_tokens(text) as n_tokens, refinery_key(text) as key from refinery_documents")


@query("""select event_id, event_type from events where event_type = (select min(event_type) from events)""")
def stream_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream without repeats: one type's events, read twice over as a stream of files with a watermark, leave once."""
    root = f"{shared_dir(spark)}/distinct-{uuid.uuid4().hex}"
    events = read(spark, sf_dir, "events").select("event_id", "event_type", "ts")
    least = events.agg(F.min("event_type")).first()[0]
    some = events.where(F.col("event_type") == least)
    some.unionByName(some).write.parquet(f"{root}/in")
    stream = spark.readStream.schema(some.schema).parquet(f"{root}/in")
    out = incremental.distinct_within(stream, ["event_id"], "36500 days").select("event_id", "event_type")
    out.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/progress").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{root}/out")


@query("""with m as (select max(ts) - interval 1 day as w from events) select event_id, ts < w as late from events, m""")
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records behind a watermark are marked, not dropped."""
    events = read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    mark = events.agg(F.max("ts") - F.expr("interval 1 day")).first()[0]
    good, late = incremental.split_late(events, F.lit(mark))
    return good.select("event_id", F.lit(False).alias("late")).unionByName(late.select("event_id", (F.col("reason") == "late_record").alias("late")))
