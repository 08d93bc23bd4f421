"""Queries of exports, of the measures over given tables, and of ablations of hygiene and sampling."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from refinery.operators import gates, hygiene, measures, sample
from refinery.operators.storage import materialize
from refinery.plans import export
from refinery.queries.base import doc_records, query, read
from refinery.records import to_records
from refinery.sources import detect

# ---- exports: what each line says, read back from the JSON ----------------------------------------------------------------------

TALKS = """t as (select conv_id, list({'role': role, 'content': text} order by turn, role, text) as turns from conversations group by conv_id)"""


def _talks(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = detect.turns_of(read(spark, sf_dir, "conversations"))
    ask, out = detect.conversation_fields(F.col("turns"))
    made = to_records(turns, {"instruction": ask, "output": out, "metadata": F.create_map(F.lit("turns"), F.to_json("turns"), F.lit("conv_id"), F.col("conv_id").cast("string"))}, "conversational", "conversations", ("conv_id",))
    return made.withColumn("id", F.col("metadata")["conv_id"])


ASKED = """a as (select conv_id, (select text from conversations u where u.conv_id = c.conv_id and role = 'user' order by turn limit 1) as i, (select text from conversations u where u.conv_id = c.conv_id and role = 'assistant' order by turn desc limit 1) as o from (select distinct conv_id from conversations) c)"""


@query(f"with {ASKED} select conv_id, i as instruction, '' as input, o as output from a where i is not null and o is not null")
def export_alpaca(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = export.lines(_talks(spark, sf_dir), "alpaca").select(F.col("id").cast("long").alias("conv_id"), F.from_json("line", "instruction string, input string, output string").alias("r"))
    return rows.select("conv_id", "r.*")


@query(f"""with {ASKED}, s as (select conv_id, turn, case role when 'user' then 'human' when 'assistant' then 'gpt' else role end as speaker, text, row_number() over (partition by conv_id order by turn) - 1 as k from conversations)
select conv_id, k::int as k, speaker, text as said from s where conv_id in (select conv_id from a where i is not null and o is not null)""")
def export_sharegpt(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = export.lines(_talks(spark, sf_dir), "sharegpt").select(F.col("id").cast("long").alias("conv_id"), F.from_json("line", "conversations array<struct<from:string,value:string>>").alias("r"))
    return rows.select("conv_id", F.posexplode("r.conversations").alias("k", "t")).select("conv_id", "k", F.col("t.from").alias("speaker"), F.col("t.value").alias("said"))


LABELLED = "(select d.doc_id, text, quality, row_number() over (partition by quality order by d.doc_id) as r from documents d join labels using (doc_id))"


def _label_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Good documents beside poor ones of the same rank."""
    from pyspark.sql import Window

    rows = read(spark, sf_dir, "documents").select("doc_id", "text").join(read(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    rows = rows.withColumn("r", F.row_number().over(Window.partitionBy("quality").orderBy("doc_id")))
    good, poor = rows.where("quality = 1"), rows.where("quality = 0").select("r", F.col("text").alias("rejected"))
    made = good.join(poor, "r").select("doc_id", F.concat(F.lit("Write text "), F.col("doc_id").cast("string")).alias("ask"), F.col("text").alias("chosen"), "rejected")
    rows = to_records(made, {"instruction": "ask", "chosen": "chosen", "rejected": "rejected", "metadata": F.create_map(F.lit("doc_id"), F.col("doc_id").cast("string"))}, "preference", "labels", ("doc_id",))
    return rows.withColumn("id", F.col("metadata")["doc_id"])


@query(f"with l as {LABELLED} select g.doc_id, 'Write text ' || g.doc_id as prompt, g.text as chosen, p.text as rejected from l g join l p on g.r = p.r and g.quality = 1 and p.quality = 0")
def export_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = export.lines(_label_pairs(spark, sf_dir), "pairs").select(F.col("id").cast("long").alias("doc_id"), F.from_json("line", "prompt string, chosen string, rejected string").alias("r"))
    return rows.select("doc_id", "r.*")


@query("""with t as (select conv_id, list({'role': role, 'content': text} order by turn) as turns, arg_min(text, turn) as first from conversations group by conv_id)
select conv_id, first as prompt, len(turns)::int as n_chosen, 1::int as n_rejected, turns[len(turns)].content as last_chosen, turns[1].content as rejected from t""")
def export_pairs_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sides that are turns stay lists of turns: the whole conversation against its first turn alone."""
    turns = detect.turns_of(read(spark, sf_dir, "conversations"))
    one = F.to_json(F.slice("turns", 1, 1))
    made = to_records(turns, {"instruction": F.get("turns", F.lit(0))["content"], "chosen": F.to_json("turns"), "rejected": one, "metadata": F.create_map(F.lit("conv_id"), F.col("conv_id").cast("string"))}, "preference", "conversations", ("conv_id",))
    side = "array<struct<role:string,content:string>>"
    rows = export.lines(made.withColumn("id", F.col("metadata")["conv_id"]), "pairs").select(F.col("id").cast("long").alias("conv_id"), F.from_json("line", f"prompt string, chosen {side}, rejected {side}").alias("r"))
    return rows.select("conv_id", "r.prompt", F.size("r.chosen").alias("n_chosen"), F.size("r.rejected").alias("n_rejected"), F.element_at("r.chosen", -1)["content"].alias("last_chosen"), F.get("r.rejected", F.lit(0))["content"].alias("rejected"))


@query("select doc_id, 'Say ' || doc_id as prompt, text as first, len(text)::double as score, 2::int as n from documents where text is not null")
def export_rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").where("text is not null")
    fields = {"instruction": F.concat(F.lit("Say "), F.col("doc_id").cast("string")), "responses": F.array("text", F.lit("none")), "reward_scores": F.array(F.length("text").cast("double"), F.lit(0.0)), "metadata": F.create_map(F.lit("doc_id"), F.col("doc_id").cast("string"))}
    made = to_records(docs, fields, "grpo", "documents", ("doc_id",)).withColumn("id", F.col("metadata")["doc_id"])
    rows = export.lines(made, "rollouts").select(F.col("id").cast("long").alias("doc_id"), F.from_json("line", "prompt string, responses array<string>, scores array<double>").alias("r"))
    return rows.select("doc_id", "r.prompt", F.get("r.responses", F.lit(0)).alias("first"), F.get("r.scores", F.lit(0)).alias("score"), F.size("r.responses").alias("n"))


@query(f"with {ASKED} select conv_id, i as query from a where i is not null")
def export_ppo(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = export.lines(_talks(spark, sf_dir), "ppo")
    return rows.select(F.col("id").cast("long").alias("conv_id"), F.get_json_object("line", "$.query").alias("query"))


@query("select doc_id, text, coalesce(source, 'documents') as source_uri, coalesce(lang, '') as lang, 0::int as steps from documents where text is not null")
def export_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = export.lines(doc_records(spark, sf_dir), "corpus").select(F.from_json("line", "id string, text string, source_uri string, metadata map<string,string>, provenance_chain array<string>").alias("r"))
    return rows.select(F.col("r.id").cast("long").alias("doc_id"), "r.text", "r.source_uri", F.col("r.metadata")["lang"].alias("lang"), F.size("r.provenance_chain").alias("steps"))


# ---- measures over the given labels -----------------------------------------------------------------------------------------------


def _verdicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars").join(read(spark, sf_dir, "labels"), "doc_id")


@query("""with v as (select lang, quality = 0 as a, toxic = 1 as b from documents join labels using (doc_id)), c as (select lang, count(*)::bigint as n, count(*) filter (a and not b)::bigint as only1, count(*) filter (b and not a)::bigint as only2, count(*) filter (a and b)::bigint as both_ from v group by lang)
select lang, n, only1, only2, both_ as "both", case when only1 + only2 + both_ > 0 then both_ / (only1 + only2 + both_)::double else 0 end as jaccard, 100.0::double * only1 / n as only1_pct, 100.0::double * only2 / n as only2_pct, 100.0::double * both_ / n as both_pct from c""")
def measure_overlap_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Overlap, Jaccard and exclusive shares of two verdicts over the same documents: poor and toxic, by language."""
    return measures.overlap(_verdicts(spark, sf_dir), F.col("quality") == 0, F.col("toxic") == 1, ("lang",))


@query("""with v as (select n_chars < 400 as bad, quality = 0 as truth from documents join labels using (doc_id)), c as (select count(*) filter (truth and bad)::bigint as tp, count(*) filter (not truth and bad)::bigint as fp, count(*) filter (truth and not bad)::bigint as fn, count(*) filter (not truth and not bad)::bigint as tn from v)
select *, case when tp + fp > 0 then tp / (tp + fp)::double end as "precision", case when tp + fn > 0 then tp / (tp + fn)::double end as recall, case when tn + fp > 0 then tn / (tn + fp)::double end as specificity from c""")
def measure_confusion_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Precision, recall and specificity of a gate (short texts) against given truth (poor quality)."""
    rows = _verdicts(spark, sf_dir)
    verdicts = rows.select(F.col("doc_id").alias("qa_id"), (F.col("n_chars") < 400).alias("rejected"))
    return measures.confusion(verdicts, rows.select(F.col("doc_id").alias("qa_id"), F.when(F.col("quality") == 0, "poor").alias("injected_type")))


@query("""with v as (select case when quality = 0 then 'poor' when toxic = 1 then 'toxic' end as kind, n_chars < 400 as hit, n_chars % 2 = 0 as rec from documents join labels using (doc_id)),
c as (select kind, count(*)::bigint as injected, count(*) filter (hit)::bigint as detected, count(*) filter (hit and rec)::bigint as recovered from v where kind is not null group by rollup (kind))
select coalesce(kind, 'all') as injected_type, injected, detected, recovered, detected / injected::double as detect_recall, recovered / injected::double as recover_recall from c where injected > 0""")
def measure_recall_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Detected and recovered shares of known faults, by type and overall."""
    rows = _verdicts(spark, sf_dir)
    verdicts = rows.select(F.col("doc_id").alias("qa_id"), (F.col("n_chars") < 400).alias("rejected"), (F.col("n_chars") % 2 == 0).alias("recovered"))
    truth = rows.select(F.col("doc_id").alias("qa_id"), F.when(F.col("quality") == 0, "poor").when(F.col("toxic") == 1, "toxic").alias("injected_type"))
    return measures.injection_recall(verdicts, truth).where("injected > 0").withColumn("injected_type", F.coalesce("injected_type", F.lit("all")))


@query("""with v as (select lang, quality, avg(n_chars) as n, avg(toxic) as t from documents join labels using (doc_id) group by all), w as (select lang, max(case when quality = 0 then n end) as n0, max(case when quality = 1 then n end) as n1, max(case when quality = 0 then t end) as t0, max(case when quality = 1 then t end) as t1 from v group by lang),
m as (select lang, 'n_chars' as metric, n0 as base, n1 as other from w union all select lang, 'toxic', t0, t1 from w) select lang, metric, round(base, 6) as base, round(other, 6) as other, round(other - base, 6) as delta, round(case when base <> 0 then (other - base) / base end, 6) as relative from m""")
def measure_deltas_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Absolute and relative change of metrics between two conditions (poor and good), by language."""
    rows = _verdicts(spark, sf_dir).groupBy("lang", F.when(F.col("quality") == 1, "good").otherwise("poor").alias("condition")).agg(F.avg("n_chars").alias("n_chars"), F.avg(F.col("toxic").cast("double")).alias("toxic"))
    out = measures.metric_deltas(rows, "lang", "condition", "poor", "good", ("n_chars", "toxic"))
    return out.withColumns({c: F.round(c, 6) for c in ("base", "other", "delta", "relative")})


@query("""with s as (select doc_id, (n_chars % 100) / 100.0::double as a, (n_chars % 7) / 7.0::double as b, (doc_id % 10) / 10.0::double as c from documents)
select doc_id, round((a + b + c) / 3, 6) as score, case when a <= b and a <= c then 'helpfulness' when b <= c then 'honesty' else 'depth' end as weakest, case when (a + b + c) / 3 < 0.5::double then 'reward_below' end as reason from s""")
def gate_reward_custom(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gate under a user's own scorer and a subset of the dimensions: mean, weakest in the order of the dimensions, and verdict."""
    made = doc_records(spark, sf_dir).withColumn("instruction", F.col("metadata")["doc_id"])
    k = F.col("instruction").cast("long")
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("n_chars").alias("_n"))
    scorer = lambda i, a: F.create_map(F.lit("helpfulness"), (F.col("_n") % 100) / F.lit(100.0), F.lit("honesty"), (F.col("_n") % 7) / F.lit(7.0), F.lit("depth"), (k % 10) / F.lit(10.0))
    out = gates.reward_gate(made.join(docs, "id"), 0.5, ("helpfulness", "honesty", "depth"), scorer)
    return out.select(F.col("id").alias("doc_id"), F.round("reward_score", 6).alias("score"), F.col("weakest_dimension").alias("weakest"), F.substring_index("rejection_reason", ":", 1).alias("reason"))


@query("""with recursive v as (select row_number() over (order by vec_id) as k, vec_id, embedding::double[] as e from embeddings), n as (select k, vec_id, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) as e from v),
p as (select y.k, list(x.k) as before from n x join n y on x.k < y.k where list_dot_product(x.e, y.e) > 0.4 group by y.k), q as (select n.k, vec_id, coalesce(before, []) as before from n left join p using (k)),
r(k, kept) as (select 0::bigint, []::bigint[] union all select q.k, case when list_has_any(kept, before) then kept else kept || [q.k] end from r join q on q.k = r.k + 1)
select vec_id as id, not list_contains((select kept from r order by k desc limit 1), k) as rejected from q""")
def gate_diversity_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The growing reference set at 0.4 in id order, against the same loop as a recursive query."""
    rows = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding", F.lit("accepted").alias("status"), F.lit(None).cast("string").alias("rejection_reason"), F.lit(None).cast("string").alias("rejecting_step"))
    return gates.diversity_gate(rows, 0.4, "exact").select("id", F.col("rejection_reason").isNotNull().alias("rejected"))


# ---- ablations ------------------------------------------------------------------------------------------------------------------


@query(r"""select doc_id, regexp_replace(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}', '<email>', 'g') as text from documents""")
def hygiene_mask(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ablation that writes the type instead of a fake, with one recogniser chosen."""
    out = hygiene.pseudonymize(doc_records(spark, sf_dir), entities=("email",), mode="mask", fields=("output",))
    return out.select(F.col("id").alias("doc_id"), F.col("output").alias("text"))


@query(r"""select doc_id, regexp_replace(text, '["''][0-9a-fA-F]{16,}["'']', '[secret]', 'g') as text from documents""")
def hygiene_redact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ablation that redacts credentials where the gate would reject the record."""
    out = hygiene.secrets_gate(doc_records(spark, sf_dir), mode="redact", fields=("output",))
    return out.select(F.col("id").alias("doc_id"), F.col("output").alias("text"))


@query(r"""with f as (select distinct doc_id, unnest(regexp_extract_all('seen ' || date '1990-01-01' + (doc_id % 5000)::int || ' at ' || (doc_id % 900 + 100) || ' Elm Street, licence AB' || lpad((doc_id % 10000000)::varchar, 7, '0'), '\b\d{4}-\d{2}-\d{2}\b|\b\d{1,5} [A-Z][a-z]+ (?:Street|Avenue|Road|Lane)\b|\b[A-Z]{2}\d{7}\b')) as v from documents)
select case when regexp_matches(v, '^\d{4}-') then 'date_time' when regexp_matches(v, 'Street$') then 'location' else 'medical_licence' end as type, count(*)::bigint as n, min(v) as least, max(v) as greatest from f group by 1""")
def hygiene_clinical(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The clinical preset finds dates, places and licence numbers planted from the id."""
    from refinery.config import PRESETS

    k = F.col("doc_id")
    text = F.concat(F.lit("seen "), F.date_add(F.lit("1990-01-01").cast("date"), (k % 5000).cast("int")).cast("string"), F.lit(" at "), (k % 900 + 100).cast("string"), F.lit(" Elm Street, licence AB"), F.lpad((k % 10000000).cast("string"), 7, "0"))
    rows = read(spark, sf_dir, "documents").select(F.explode(hygiene.pii_findings(text, PRESETS["clinical"]["pii_entities"])).alias("f"))
    return rows.groupBy(F.col("f.type").alias("type")).agg(F.count(F.lit(1)).alias("n"), F.min("f.value").alias("least"), F.max("f.value").alias("greatest"))


@query("""with g as (select * from (values ('en', 0.4::double), ('de', 0.6)) as g(lang, share)), q as (select lang, floor(share * (select count(*) from documents) + 1e-9) as quota from g),
r as (select doc_id, lang, row_number() over (partition by lang order by md5('0|' || doc_id), doc_id) as r from documents)
select doc_id, case when quota is null or r > quota then 'downsampled' end as reason from r left join q using (lang)""")
def sample_untargeted_reject(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Categories without a target are rejected."""
    rows = doc_records(spark, sf_dir).withColumn("lang", F.col("metadata")["lang"])
    out = sample.stratified(rows, "lang", {"en": 0.4, "de": 0.6}, untargeted="reject")
    return out.select(F.col("id").alias("doc_id"), F.substring_index("rejection_reason", ":", 1).alias("reason"))


@query("select model, count(*)::bigint as calls, count(*) filter (failed)::bigint as failed, sum(tokens)::bigint as prompt_tokens, sum(2 * tokens)::bigint as completion_tokens from (select 'm' || doc_id % 3 as model, doc_id % 5 = 0 as failed, n_chars as tokens from documents) group by model")
def measure_call_usage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Calls, failures and tokens by model, from a ledger made of the documents."""
    d = read(spark, sf_dir, "documents")
    ledger = d.select(F.concat(F.lit("m"), (F.col("doc_id") % 3).cast("string")).alias("model"), F.when(F.col("doc_id") % 5 == 0, "timeout").alias("error"), F.col("n_chars").alias("prompt_tokens"), (2 * F.col("n_chars")).alias("completion_tokens"), F.lit(0.1).alias("latency"))
    return materialize(measures.call_usage(ledger).drop("latency"), "usage")
