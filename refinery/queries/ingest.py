"""Queries of reading, mapping, detection, chunking, schema and cleaning."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from refinery.functions import text as tx
from refinery.operators import generation
from refinery.operators.clean import clean
from refinery.operators.schema_gate import schema_gate
from refinery.operators.storage import materialize, shared_dir
from refinery.queries.base import doc_records, query, read
from refinery.records import append_provenance, prefix_violations, stable_id, to_records
from refinery.sources import detect, readers


@query("""with h as (select doc_id, sha256('documents' || chr(31) || doc_id::varchar) as h from documents)
select doc_id, h[1:8] || '-' || h[9:12] || '-4' || h[14:16] || '-' || translate(h[17:17], '0123456789abcdef', '89ab89ab89ab89ab') || h[18:20] || '-' || h[21:32] as id from h""")
def ingest_stable_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").select("doc_id", stable_id(F.lit("documents"), F.col("doc_id")).alias("id"))


@query("select doc_id, 'language_modeling' as task_type, length(text)::int as n_output, true as no_instruction from documents")
def ingest_field_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mapping comes from detection: text is an alias of output."""
    docs = read(spark, sf_dir, "documents")
    found = detect.detect_format(docs.select("doc_id", "text"))
    rows = to_records(docs, {**found.mapping, "metadata": F.create_map(F.lit("doc_id"), F.col("doc_id").cast("string"))}, found.task_type, "documents", ("doc_id",))
    return rows.select(F.col("metadata")["doc_id"].cast("long").alias("doc_id"), "task_type", F.length("output").alias("n_output"), F.col("instruction").isNull().alias("no_instruction"))


ROUND_TRIP = "select conv_id, turn, role, text from conversations"


def _written(df: DataFrame, fmt: str, **options) -> str:
    path = f"{shared_dir(df.sparkSession)}/roundtrip-{uuid.uuid4().hex}"
    df.write.options(**options).format(fmt).save(path)
    return path


@query(ROUND_TRIP)
def ingest_jsonl_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _written(read(spark, sf_dir, "conversations"), "json")
    return readers.read_source(spark, readers.SourceSpec("jsonl", path)).select("conv_id", "turn", "role", "text")


@query(ROUND_TRIP)
def ingest_csv_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts hold line ends, quotes and commas."""
    path = _written(read(spark, sf_dir, "conversations"), "csv", header=True, quote='"', escape='"', quoteAll=True)
    rows = readers.read_source(spark, readers.SourceSpec("csv", path))
    return rows.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")


@query(ROUND_TRIP)
def ingest_tsv_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _written(read(spark, sf_dir, "conversations"), "csv", header=True, sep="\t", quote='"', escape='"', quoteAll=True)
    rows = readers.read_source(spark, readers.SourceSpec("tsv", path))
    return rows.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")


@query("select r_regionkey, r_name from region")
def ingest_json_data_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An object that holds the array of rows under a key."""
    one = read(spark, sf_dir, "region").agg(F.collect_list(F.struct("r_regionkey", "r_name")).alias("rows"))  # a fixed table of five rows
    path = _written(one, "json")
    rows = readers.read_source(spark, readers.SourceSpec("json", path, {"data_key": "rows"}))
    return rows.select(F.col("r_regionkey").cast("int").alias("r_regionkey"), "r_name")


@query(ROUND_TRIP)
def ingest_hub_layout(spark: SparkSession, sf_dir: str) -> DataFrame:
    root = f"{shared_dir(spark)}/hub-{uuid.uuid4().hex}"
    read(spark, sf_dir, "conversations").write.parquet(f"{root}/chats/main/train")
    return readers.read_source(spark, readers.SourceSpec("hub", f"{root}/chats", subset="main", split="train")).select("conv_id", "turn", "role", "text")


@query("select 'documents' as source, count(*)::bigint as n from documents union all select 'benchmark', count(*) from benchmark")
def ingest_multi_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = readers.read_all(spark, [readers.SourceSpec("parquet", f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark")])
    return rows.groupBy(F.regexp_extract("src_uri", r"([a-z]+)\.parquet/[^/]*$", 1).alias("source")).agg(F.count(F.lit(1)).alias("n"))


@query("""with j as (select doc_id, case when doc_id % 7 = 0 then false else true end as good from documents) select case when good then 'accepted' else 'parse_failed' end as verdict, count(*)::bigint as n from j group by 1""")
def ingest_parse_failures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every seventh line is cut short: it is kept as a rejected row, not dropped."""
    docs = read(spark, sf_dir, "documents").select("doc_id", F.to_json(F.struct("doc_id", "text")).alias("value"))
    path = f"{shared_dir(spark)}/broken-{uuid.uuid4().hex}"
    docs.select(F.when(F.col("doc_id") % 7 == 0, F.lit('{"doc_id": 1, "text": "cut')).otherwise(F.col("value")).alias("value")).write.text(path)
    rows = readers.read_source(spark, readers.SourceSpec("jsonl", path, {"schema": read(spark, sf_dir, "documents").select("doc_id", "text").schema}))
    return rows.groupBy(F.when(F.col("corrupt").isNull(), "accepted").otherwise("parse_failed").alias("verdict")).agg(F.count(F.lit(1)).alias("n"))


@query("""with t as (select conv_id, turn, case lower(role) when 'human' then 'user' when 'gpt' then 'assistant' else lower(role) end as role, text from conversations)
select conv_id, count(*)::bigint as n_turns, (select text from t u where u.conv_id = t.conv_id and role = 'user' order by turn limit 1) as instruction,
  (select text from t u where u.conv_id = t.conv_id and role = 'assistant' order by turn desc limit 1) as output from t group by conv_id""")
def ingest_conversations_to_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = detect.turns_of(read(spark, sf_dir, "conversations"))
    ask, out = detect.conversation_fields(F.col("turns"))
    return rows.select("conv_id", F.size("turns").cast("long").alias("n_turns"), ask.alias("instruction"), out.alias("output"))


@query("""select given, case given when 'human' then 'user' when 'gpt' then 'assistant' else given end as role, n from
(select case when conv_id % 2 = 0 then case role when 'user' then 'human' when 'assistant' then 'gpt' else role end else role end as given, count(*)::bigint as n from conversations group by 1)""")
def ingest_role_normalize(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Half of the conversations are put in the other convention first."""
    other = F.when(F.col("role") == "user", "human").when(F.col("role") == "assistant", "gpt").otherwise(F.col("role"))
    rows = read(spark, sf_dir, "conversations").select(F.when(F.col("conv_id") % 2 == 0, other).otherwise(F.col("role")).alias("given"))
    return rows.groupBy("given").agg(F.count(F.lit(1)).alias("n")).select("given", detect.normalize_role(F.col("given")).alias("role"), "n")


@query("""select * from (values ('exact names', 'instruction_following', 'HIGH'), ('aliases', 'instruction_following', 'MEDIUM'), ('pairs', 'preference', 'HIGH'), ('text only', 'language_modeling', 'MEDIUM'),
  ('flat conversations', 'language_modeling', 'MEDIUM'), ('turn lists', 'conversational', 'HIGH'), ('numbers', 'none', 'UNKNOWN')) as t(frame, task_type, tier)""")
def ingest_detect(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Confidence of detection over frames made from the tables."""
    docs = read(spark, sf_dir, "documents").where(F.trim("text") != "").select("doc_id", "text")
    turns = detect.turns_of(read(spark, sf_dir, "conversations"))
    frames = {
        "exact names": docs.select(F.col("text").alias("instruction"), F.col("text").alias("output")),
        "aliases": docs.select(F.col("text").alias("question"), F.col("text").alias("answer")),
        "pairs": docs.select(F.col("text").alias("chosen"), F.col("text").alias("rejected")),
        "text only": docs,
        "flat conversations": docs.select(F.col("text").alias("conversations"), F.col("text").alias("body")),
        "turn lists": turns.select(F.col("turns").alias("conversations")),
        "numbers": docs.select("doc_id"),
    }
    found = [(name, (d := detect.detect_format(df)).task_type or "none", d.tier) for name, df in frames.items()]
    return spark.createDataFrame(found, "frame string, task_type string, tier string")


@query("""with d as (select doc_id, list_filter(string_split_regex(text, '\\s+'), lambda w: w <> '') as w from documents)
select doc_id, k::int as chunk_no, least(len(w) - k * 462, 512)::bigint as n_tokens, array_to_string(w[k * 462 + 1 : k * 462 + 512], ' ') as chunk
from d, lateral (select unnest(range(0, case when len(w) = 0 then 0 else greatest(0, len(w) - 51) // 462 + 1 end)) as k)""")
def ingest_chunk_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = generation.chunk_fixed(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"), 512, 50)
    return rows.withColumnRenamed("id", "doc_id")


@query("""with d as (select doc_id, list_filter(string_split(text, chr(10)), lambda p: trim(p) <> '') as p from documents), e as (select doc_id, unnest(p) as chunk, unnest(range(0, len(p))) as chunk_no from d)
select doc_id, chunk_no::int as chunk_no, trim(chunk) as chunk, len(list_filter(string_split_regex(chunk, '\\s+'), lambda w: w <> ''))::bigint as n_tokens from e""")
def ingest_chunk_paragraph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return generation.chunk_paragraph(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")).withColumnRenamed("id", "doc_id")


@query()
def ingest_chunk_headings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return generation.chunk_headings(read(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), "html")).withColumnRenamed("id", "page_id")


@query("""with t as (select doc_id, list_filter(list_transform(string_split(array_to_string(list_transform(string_split(text, chr(10)), lambda x: case when len(string_split(x, '|')) >= 3 then x else chr(1) end), chr(10)), chr(1)), lambda x: regexp_replace(x, '^\\n+|\\n+$', '', 'g')), lambda x: x <> '') as t from documents)
select doc_id, unnest(range(0, len(t)))::int as table_no, unnest(t) as "table" from t""")
def ingest_extract_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    return generation.extract_tables(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")).withColumnRenamed("id", "doc_id")


WORDS = "len(list_filter(string_split_regex(text, '\\s+'), lambda w: w <> ''))"


@query(f"select doc_id, {WORDS}::bigint as n_tokens from documents")
def schema_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").select("doc_id", tx.token_count(F.col("text")).alias("n_tokens"))


@query(f"""with n as (select doc_id, text, {WORDS} as n from documents)
select doc_id, case when trim(text) = '' then 'schema_missing:output' when n < 10 then 'schema_too_short:' || n when n > 4096 then 'schema_too_long:' || n end as reason from n""")
def schema_gate_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return schema_gate(doc_records(spark, sf_dir)).select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


@query("""with t as (select conv_id, turn, role, text from conversations), c as (select conv_id, (select text from t u where u.conv_id = t.conv_id and role = 'user' order by turn limit 1) as i, (select text from t u where u.conv_id = t.conv_id and role = 'assistant' order by turn desc limit 1) as o from t group by conv_id)
select conv_id, case when i is null or trim(i) = '' then 'schema_missing:instruction' when o is null or trim(o) = '' then 'schema_missing:output' end as reason from c""")
def schema_gate_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = detect.turns_of(read(spark, sf_dir, "conversations"))
    ask, out = detect.conversation_fields(F.col("turns"))
    made = to_records(rows, {"instruction": ask, "output": out, "metadata": F.create_map(F.lit("conv_id"), F.col("conv_id").cast("string"))}, "conversational", "conversations", ("conv_id",))
    return schema_gate(made, 0, 1_000_000).select(F.col("metadata")["conv_id"].cast("long").alias("conv_id"), F.col("rejection_reason").alias("reason"))


_STRIP = "regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script\\b.*?</script\\s*>', ' ', 'g'), '(?is)<style\\b.*?</style\\s*>', ' ', 'g'), '(?s)<!--.*?-->', ' ', 'g'), '</?[A-Za-z!][^>]*>', ' ', 'g')"
for _name, _char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&apos;", "''"), ("&nbsp;", " "), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&")):
    _STRIP = f"replace({_STRIP}, '{_name}', '{_char}')"


@query(f"select page_id, trim(regexp_replace({_STRIP}, '[ \\t\\n\\r\\x0b\\f]+', ' ', 'g')) as text from pages")
def clean_html_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages").select("page_id", F.trim(F.regexp_replace(tx.strip_html(F.col("html")), "[ \\t\\n\\r\\x0B\\f]+", " ")).alias("text"))


@query("select doc_id, trim(regexp_replace(replace(text, ' ', chr(9) || ' ' || chr(160)), '[ \\t\\n\\r\\x0b\\f\\x{a0}]+', ' ', 'g')) as text from documents")
def clean_whitespace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every blank is first made a tab, a blank and a no-break space."""
    docs = read(spark, sf_dir, "documents").select("doc_id", F.replace("text", F.lit(" "), F.lit("\t  ")).alias("text"))
    return docs.select("doc_id", tx.collapse_space(F.col("text"), keep_newlines=False).alias("text"))


@query("select doc_id, text from documents")
def clean_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Control characters put after every blank are taken out again; line ends stay."""
    docs = read(spark, sf_dir, "documents").select("doc_id", F.replace("text", F.lit(" "), F.lit("\x07 \x7f\u0085")).alias("text"))
    return docs.select("doc_id", tx.strip_control(F.col("text")).alias("text"))


@query("select doc_id, text from documents where not regexp_matches(text, '[^\\x{0}-\\x{ff}]')")
def clean_mojibake(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts put through the fault (UTF-8 read as Latin-1) come back, wherever Latin-1 holds them."""
    docs = read(spark, sf_dir, "documents").where(~F.col("text").rlike("[^\u0000-ÿ]"))
    broken = docs.select("doc_id", F.decode(F.encode("text", "UTF-8"), "ISO-8859-1").alias("text"))
    return broken.select("doc_id", tx.repair_mojibake(F.col("text")).alias("text"))


@query("select doc_id, nfc_normalize(text) as text from documents")
def clean_unicode(spark: SparkSession, sf_dir: str) -> DataFrame:
    from refinery.operators.clean import nfc

    return nfc(read(spark, sf_dir, "documents").select("doc_id", "text"), ("text",))


@query("select count(*)::bigint as records, count(*) * 5::bigint as chain_entries, 0::bigint as violations from documents")
def clean_provenance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One record of provenance for each transform, after what was there."""
    before = materialize(append_provenance(doc_records(spark, sf_dir), "ingest"), "before")
    after = materialize(clean(before), "after")
    bad = prefix_violations(before, after).agg(F.count(F.lit(1)).alias("violations"))
    counts = after.agg(F.count(F.lit(1)).alias("records"), F.sum(F.size("provenance_chain") - 1).cast("long").alias("chain_entries"))
    return counts.join(bad)
