"""Queries of deduplication, sampling, hygiene, runs and their counts."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from refinery.config import CurationConfig
from refinery.functions import text as tx
from refinery.operators import dedup, hygiene, sample
from refinery.operators.storage import materialize, shared_dir
from refinery.plans.run import Curation
from refinery.queries.base import doc_records, query, read
from refinery.records import rejection_breakdown

KEY = "sha256(trim(regexp_replace(lower(text), '\\s+', ' ', 'g')))"


@query(f"""with k as (select doc_id, {KEY} as key from documents), f as (select doc_id, min(doc_id) over (partition by key) as best from k)
select doc_id, case when best <> doc_id then 'exact_duplicate:' || best end as reason from f""")
def dedup_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup.dedup_exact(doc_records(spark, sf_dir)).select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


@query(f"""with k as (select {KEY} as key, count(*) as n from documents group by 1) select 'exact_duplicate' as code, sum(n - 1)::bigint as removed, count(*)::bigint as survivors, max(n - 1)::bigint as largest from k where n > 1""")
def dedup_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup.dedup_stats(dedup.dedup_exact(doc_records(spark, sf_dir)))


def _normal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), tx.normal_form(F.col("text")).alias("text"))


@query()
def dedup_jaccard_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Character 3-gram pairs at 0.85 or more, by a banding that finds nearly all; tests hold it against brute force."""
    return dedup.near_pairs(_normal(spark, sf_dir), n=3, threshold=0.85, bands=(16, 8)).select("a", "b", F.round("similarity", 6).alias("similarity"))


@query()
def dedup_minhash_auto_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The default: bands chosen from the threshold by area. Pairs at the threshold are lost; runs use run_bands."""
    return dedup.near_pairs(_normal(spark, sf_dir), n=3, threshold=0.85, bands=dedup.choose_bands(128, 0.85)).select("a", "b", F.round("similarity", 6).alias("similarity"))


@query()
def dedup_minhash_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup.dedup_minhash(doc_records(spark, sf_dir), bands=(16, 8))
    return out.select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


@query()
def dedup_minhash_component(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dedup.dedup_minhash(doc_records(spark, sf_dir), bands=(16, 8), policy="component")
    return out.select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


#: Thresholds of near-duplicates, the highest first, and the characters of an edited word.
THRESHOLDS, EDIT = (0.9, 0.85, 0.8, 0.7), 10

# the areas of every banding of 128 places, by the midpoint rule, as the operator takes them
BANDINGS = """grid as (select threshold, b, r from (select distinct threshold from d), (select unnest(range(1, 129)) as r) as x, (select unnest(range(1, 129)) as b) as y where b * r <= 128),
area as (select threshold, b, r, sum(1 - pow(1 - pow(threshold * (k + 0.5) / 200, r), b)) * threshold / 200 as fp, sum(pow(1 - pow(threshold + (1 - threshold) * (k + 0.5) / 200, r), b)) * (1 - threshold) / 200 as fn from grid, (select unnest(range(0, 200)) as k) as z group by threshold, b, r),
best as (select threshold, arg_min(b, fp + fn) as bands, arg_min(r, fp + fn) as "rows" from area group by threshold)"""


@query(f"""with n as (select greatest(coalesce(length(text), 0) - 2, 1)::double as g from documents), e as (select (g - {EDIT} - 2) / (g + {EDIT} + 2) as kept from n),
d as (select case {" ".join(f"when kept >= {t}::double then {t}::double" for t in THRESHOLDS[:-1])} else {THRESHOLDS[-1]}::double end as threshold, count(*) as documents from e group by 1), {BANDINGS}
select threshold, documents, bands::int as bands, "rows"::int as "rows" from d join best using (threshold)""")
def dedup_choose_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document's threshold is the highest of four that its text still meets beside itself with one word edited (character 3-grams); the documents of each
    threshold, and the bands and rows that are chosen for it."""
    grams = F.greatest(F.coalesce(F.char_length("text"), F.lit(0)) - 2, F.lit(1)).cast("double")
    kept = (grams - EDIT - 2) / (grams + EDIT + 2)
    threshold = F.lit(THRESHOLDS[-1])
    for t in reversed(THRESHOLDS[:-1]):
        threshold = F.when(kept >= t, t).otherwise(threshold)

    @F.udf("bands int, rows int")
    def chosen(t):
        return dedup.choose_bands(128, t)

    found = read(spark, sf_dir, "documents").select(threshold.alias("threshold")).groupBy("threshold").agg(F.count(F.lit(1)).alias("documents"))
    return found.withColumn("b", chosen("threshold")).select("threshold", "documents", "b.bands", "b.rows")


COSINES = """with v as (select vec_id, embedding::double[] as e from embeddings), n as (select vec_id, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) as e from v)
select x.vec_id as a, y.vec_id as b, round(list_dot_product(x.e, y.e), 6) as cosine from n x join n y on x.vec_id < y.vec_id where list_dot_product(x.e, y.e) > 0.4"""


@query(COSINES)
def dedup_embedding_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pairs above 0.4 (nothing in the table reaches 0.92), by blocks at every size."""
    v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    return dedup.vector_pairs(v, None, 0.4, "exact").select("a", "b", F.round("cosine", 6).alias("cosine"))


@query()
def dedup_embedding_lsh(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The approximate index on the same pairs."""
    v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    return dedup.vector_pairs(v, None, 0.4, "lsh", tables=24, bits=5).select("a", "b", F.round("cosine", 6).alias("cosine"))


@query()
def dedup_ann_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of brute force, of the index, and the index's recall."""
    v = materialize(read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding"), "vectors")
    exact = dedup.vector_pairs(v, None, 0.4, "exact").select("a", "b", F.lit(1).alias("exact"))
    lsh = dedup.vector_pairs(v, None, 0.4, "lsh", tables=24, bits=5).select("a", "b", F.lit(1).alias("lsh"))
    both = exact.join(lsh, ["a", "b"], "left")
    return both.agg(F.count(F.lit(1)).alias("exact_pairs"), F.count("lsh").alias("found"), (F.count("lsh") / F.greatest(F.count(F.lit(1)), F.lit(1))).alias("recall"))


@query()
def dedup_cross_run_embedding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two runs with a persistent index: even ids, then odd ids."""
    store = dedup.IndexStore(spark, f"{shared_dir(spark)}/index-{uuid.uuid4().hex}")
    v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding", F.lit("accepted").alias("status"), F.lit(None).cast("string").alias("rejection_reason"), F.lit(None).cast("string").alias("rejecting_step"))
    out = None
    for run in (0, 1):
        done = dedup.dedup_embedding(v.where(F.col("id") % 2 == run), 0.4, store, f"run-{run}").select("id", F.lit(run).alias("run"), "rejection_reason")
        out = done if out is None else out.unionByName(done)
    return out


@query(f"""with k as (select doc_id, {KEY} as key from documents), e as (select distinct key from k where doc_id % 2 = 0),
f as (select doc_id, doc_id % 2 = 1 and key in (select key from e) as seen, min(doc_id) over (partition by key, doc_id % 2) as best from k)
select doc_id, case when seen then 'seen_in_earlier_run' when best <> doc_id then 'exact_duplicate' end as reason from f""")
def dedup_cross_run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same texts in two runs: even ids first, then odd ids against what the first run kept."""
    from refinery.streaming.incremental import dedup_batch

    root = f"{shared_dir(spark)}/runs-{uuid.uuid4().hex}"
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    for run in (0, 1):
        dedup_batch(docs.where(F.col("doc_id") % 2 == run), run, root)
    return spark.read.parquet(f"{root}/rows").select("doc_id", "reason")


GRAMS = """list_distinct(list_transform(range(1, greatest(len(w) - 7, 1) + 1), lambda i: array_to_string(w[i : i + 7], ' ')))"""


@query(f"""with d as (select doc_id, list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '') as w from documents), b as (select item_id, list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '') as w from benchmark),
dg as (select doc_id, unnest({GRAMS}) as g from d), bg as (select item_id, unnest({GRAMS}) as g, len({GRAMS}) as n from b)
select doc_id as left_id, item_id as right_id, round(count(*) / max(n)::double, 6) as coverage from dg join bg using (g) group by 1, 2 having count(*) / max(n)::double >= 0.5""")
def dedup_contamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    items = read(spark, sf_dir, "benchmark").select(F.col("item_id").alias("id"), "text")
    return dedup.match_near(docs, items).select("left_id", "right_id", F.round("coverage", 6).alias("coverage"))


TARGET = {"en": 0.4, "de": 0.2, "fr": 0.2, "es": 0.2}


def _lang_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return doc_records(spark, sf_dir).withColumn("lang", F.col("metadata")["lang"])


GOALS = "(values ('en', 0.4::double), ('de', 0.2), ('fr', 0.2), ('es', 0.2)) as g(lang, share)"


@query(f"""with q as (select lang, floor(share * (select count(*) from documents) + 1e-9) as quota from {GOALS}),
r as (select doc_id, lang, row_number() over (partition by lang order by md5('0|' || doc_id), doc_id) as r from documents)
select doc_id, case when r > quota then 'downsampled:' || lang end as reason from r left join q using (lang)""")
def sample_stratified(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sample.stratified(_lang_records(spark, sf_dir), "lang", TARGET).select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


@query(f"""with c as (select lang, count(*) as n from documents group by lang), b as (select min(n / share) as base from {GOALS} join c using (lang)), q as (select lang, floor(share * base + 1e-9) as quota from {GOALS}, b),
r as (select doc_id, lang, row_number() over (partition by lang order by md5('0|' || doc_id), doc_id) as r from documents)
select doc_id, case when r > quota then 'downsampled:' || lang end as reason from r left join q using (lang)""")
def sample_stratified_feasible(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sample.stratified(_lang_records(spark, sf_dir), "lang", TARGET, basis="feasible").select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


@query(f"""with q as (select lang, floor(share * (select count(*) from documents) + 1e-9)::bigint as wanted from {GOALS}), n as (select lang, count(*) as n from documents group by lang)
select lang, (wanted - coalesce(n, 0))::bigint as shortfall from q left join n using (lang) where wanted > coalesce(n, 0)""")
def sample_shortfalls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sample.shortfalls(_lang_records(spark, sf_dir), "lang", TARGET)


@query("select doc_id, case when row_number() over (order by md5('0|' || doc_id), doc_id) > 300 then 'truncated' end as reason from documents")
def sample_truncate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sample.truncate(doc_records(spark, sf_dir), 300).select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


@query("""with r as (select doc_id, row_number() over (order by md5('7|' || doc_id), doc_id) as r, count(*) over () as n from documents)
select doc_id, case when r <= round_even(0.8 * n, 0) then 'train' when r <= round_even(0.9 * n, 0) then 'valid' else 'test' end as split from r""")
def sample_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sample.split_output(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("id")), {"train": 0.8, "valid": 0.1, "test": 0.1}, 7).select(F.col("id").alias("doc_id"), "split")


TOKENS = """t as (select distinct doc_id, unnest(regexp_extract_all(text, '["'']([0-9a-fA-F]{16,})["'']', 1)) as token from documents),
c as (select doc_id, token, unnest(string_split(token, '')) as ch from t), p as (select doc_id, token, ch, count(*)::double as k from c group by all),
e as (select doc_id, token, -sum(k / length(token) * log2(k / length(token))) as bits from p group by all)"""


@query(f"with {TOKENS} select doc_id, token, round(bits, 6) as bits from e")
def hygiene_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = read(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all("text", F.lit(hygiene.QUOTED_HEX), F.lit(1)))).alias("token"))
    return found.select("doc_id", "token", F.round(tx.shannon_entropy(F.col("token")), 6).alias("bits"))


@query(f"with {TOKENS}, h as (select distinct doc_id from e where bits > 3.0) select d.doc_id, case when h.doc_id is not null then 'secrets:hex_entropy' end as reason from documents d left join h using (doc_id)")
def hygiene_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hygiene.secrets_gate(doc_records(spark, sf_dir)).select(F.col("id").alias("doc_id"), F.col("rejection_reason").alias("reason"))


@query(f"with {TOKENS}, l as (select * from (values (2.0::double), (3.0), (3.5), (3.8), (4.5)) as l(hex_limit)) select hex_limit, (select count(*) from e where bits > hex_limit)::bigint as tokens, (select count(distinct doc_id) from e where bits > hex_limit)::bigint as documents from l")
def hygiene_secrets_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens and documents caught by the hex limit; at 4.5 bits, above the most that hex can hold, nothing is."""
    bits = materialize(hygiene_entropy(spark, sf_dir), "bits")
    limits = spark.createDataFrame([(2.0,), (3.0,), (3.5,), (3.8,), (4.5,)], "hex_limit double")
    hits = bits.join(F.broadcast(limits), F.col("bits") > F.col("hex_limit")).groupBy("hex_limit").agg(F.count(F.lit(1)).alias("tokens"), F.countDistinct("doc_id").alias("documents"))
    return limits.join(hits, "hex_limit", "left").select("hex_limit", F.coalesce("tokens", F.lit(0)).alias("tokens"), F.coalesce("documents", F.lit(0)).alias("documents"))


@query("""select (doc_id % 8)::int as kind, case (doc_id % 8)::int when 0 then 'aws_key' when 1 then 'git_token' when 2 then 'private_key' when 3 then 'jwt' when 4 then 'saas_token' when 5 then 'hex_entropy' when 6 then 'keyword' else 'none' end as detector, count(*)::bigint as n from documents group by all""")
def hygiene_secrets_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each credential shape, made from the id, is named by its detector (code mode on); prose about secrets isn't. The hex is 64 digits: of 32, one in
    about 9,500 has 3.0 bits or less and so isn't the shape that the detector is for."""
    k, m = F.col("doc_id"), F.md5(F.col("doc_id").cast("string"))
    text = (
        F.when(k % 8 == 0, F.concat(F.lit("AKIA"), F.upper(F.substring(m, 1, 16)))).when(k % 8 == 1, F.concat(F.lit("ghp_"), F.substring(F.concat(m, m), 1, 36))).when(k % 8 == 2, "-----BEGIN RSA PRIVATE KEY-----")
        .when(k % 8 == 3, F.concat(F.lit("eyJ"), m, F.lit(".eyJ"), m, F.lit("."), m)).when(k % 8 == 4, F.concat(F.lit("xoxb-"), m)).when(k % 8 == 5, F.concat(F.lit('"'), F.sha2(k.cast("string"), 256), F.lit('"'))).when(k % 8 == 6, "password = hunter").otherwise("the secret is out")
    )
    rows = read(spark, sf_dir, "documents").select((k % 8).cast("int").alias("kind"), hygiene.secret_counts(F.concat(F.lit("see "), text, F.lit(" there")), code_mode=True).alias("hits"))
    return rows.groupBy("kind", F.coalesce(F.try_element_at(F.map_keys("hits"), F.lit(1)), F.lit("none")).alias("detector")).agg(F.count(F.lit(1)).alias("n"))


LUHN = """(select sum(case when (i - 1) % 2 = 0 then d else case when d * 2 > 9 then d * 2 - 9 else d * 2 end end) from (select unnest(string_split(reverse(v), ''))::int as d, unnest(range(1, length(v) + 1)) as i)) % 10 = 0"""


@query(f"""with f as (select distinct doc_id, 'email' as type, unnest(regexp_extract_all(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\\.[A-Za-z0-9-]+)*\\.[A-Za-z]{{2,}}')) as v from documents
 union all select distinct doc_id, 'phone', unnest(regexp_extract_all(text, '\\+\\d{{1,3}} \\(\\d{{3}}\\) \\d{{3}}-\\d{{4}}|\\(\\d{{3}}\\) \\d{{3}}-\\d{{4}}')) from documents
 union all select distinct doc_id, 'ip_address', unnest(regexp_extract_all(text, '\\b(?:(?:25[0-5]|2[0-4]\\d|1?\\d?\\d)\\.){{3}}(?:25[0-5]|2[0-4]\\d|1?\\d?\\d)\\b')) from documents),
c as (select distinct doc_id, unnest(regexp_extract_all(text, '\\b\\d{{16}}\\b')) as v from documents), g as (select doc_id, v from c where {LUHN})
select type, count(distinct doc_id)::bigint as documents, count(*)::bigint as findings from (select doc_id, type, v from f union all select doc_id, 'credit_card', v from g) group by type""")
def hygiene_pii_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "documents").select("doc_id", F.explode(hygiene.pii_findings(F.col("text"))).alias("f"))
    return rows.groupBy(F.col("f.type").alias("type")).agg(F.countDistinct("doc_id").alias("documents"), F.count(F.lit(1)).alias("findings"))


@query("""select count(*)::bigint as records, 0::bigint as still_there, count(*) filter (where regexp_matches(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\\.[A-Za-z0-9-]+)*\\.[A-Za-z]{2,}'))::bigint as with_fake_mail from documents""")
def hygiene_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """After replacement no original address is left, and fakes stand where originals stood."""
    before = doc_records(spark, sf_dir)
    mail = hygiene.PII_PATTERNS["email"][0]
    after = hygiene.pseudonymize(before.withColumn("instruction", F.array_join(F.regexp_extract_all("output", F.lit(mail), F.lit(0)), " ")), fields=("output",))
    was = F.filter(F.split(F.coalesce("instruction", F.lit("")), " "), lambda x: x != "")
    left = F.exists(was, lambda v: F.col("output").contains(v))
    return after.agg(F.count(F.lit(1)).alias("records"), F.count_if(left).alias("still_there"), F.count_if(F.col("output").contains("@example.org")).alias("with_fake_mail"))


def labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, text, toxic, half (0: the lexicon's training half)."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "lang").join(read(spark, sf_dir, "labels"), "doc_id")
    return docs.withColumn("half", tx.hash_int(2, F.lit("tox"), F.col("doc_id")))


LEXICON = """h as (select doc_id, text, lang, toxic, (('0x' || md5('tox|' || doc_id)[1:8])::bigint % 2)::int as half from documents join labels using (doc_id)),
w as (select doc_id, toxic, half, unnest(list_distinct(list_filter(string_split_regex(regexp_replace(lower(text), '[.,;:!?"]', '', 'g'), '\\s+'), lambda x: x <> ''))) as word from h),
lex as (select word from w where half = 0 group by word having sum(toxic) >= greatest(3, ceil(0.02::double * (select count(*) from h where half = 0 and toxic = 1))) and sum(toxic) >= 0.8::double * count(*))"""


@query(f"""with {LEXICON}, k as (select doc_id, count(*) as hits from w join lex using (word) group by doc_id), s as (select h.*, round(greatest(1 - pow(0.4::double, coalesce(hits, 0)), 1 - pow(0.4::double, coalesce(hits, 0))), 6) as toxicity from h left join k using (doc_id))
select doc_id, half, toxic, toxicity, toxicity > 0.5 as rejected from s""")
def hygiene_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The lexicon is learned on one half of the labels; scores and verdicts are for both."""
    rows = labelled(spark, sf_dir)
    lexicon = hygiene.learn_lexicon(rows.where("half = 0").select("doc_id", "text", "toxic"))
    out = hygiene.toxicity_scores(rows.withColumnRenamed("doc_id", "id"), lexicon, text=F.col("text"))
    return out.select(F.col("id").alias("doc_id"), "half", "toxic", F.round("toxicity", 6).alias("toxicity"), (F.col("toxicity") > 0.5).alias("rejected"))


@query(f"""with {LEXICON}, v as (select doc_id, unnest(list_distinct(list_filter(string_split_regex(regexp_replace(lower(text), '[.,;:!?"]', '', 'g'), '\\s+'), lambda x: x <> ''))) as word from documents),
k as (select doc_id, count(*) as hits from v join lex using (word) group by doc_id) select doc_id, case when 1 - pow(0.4::double, coalesce(hits, 0)) > 0.5 then 'toxic_classifier' end as reason from documents left join k using (doc_id)""")
def hygiene_toxicity_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gate over all documents, labelled or not."""
    rows = labelled(spark, sf_dir)
    lexicon = hygiene.learn_lexicon(rows.where("half = 0").select("doc_id", "text", "toxic"))
    out = hygiene.toxicity_gate(doc_records(spark, sf_dir), lexicon)
    return out.select(F.col("id").alias("doc_id"), F.substring_index("rejection_reason", ":", 1).alias("reason"))


@query(f"""with {LEXICON}, k as (select doc_id, count(*) as hits from w join lex using (word) group by doc_id), s as (select h.*, 1 - pow(0.4::double, coalesce(hits, 0)) as t from h left join k using (doc_id)), b as (select * from (values (0.1::double), (0.2)) as b(pass_below))
select pass_below, half, count(*) filter (where t >= pass_below and t <= 0.5)::bigint as escalated, count(*) filter (where t > 0.5 and toxic = 1)::bigint as tp, count(*) filter (where t > 0.5 and toxic = 0)::bigint as fp, count(*) filter (where toxic = 1)::bigint as toxic from s, b group by all""")
def hygiene_toxicity_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How the band that goes to a judge moves with the pass threshold, on the training and the unseen half."""
    rows = materialize(hygiene_toxicity(spark, sf_dir), "toxicity")
    t, toxic = F.col("toxicity"), F.col("toxic") == 1
    rows = rows.withColumn("pass_below", F.explode(F.array(F.lit(0.1), F.lit(0.2))))
    return rows.groupBy("pass_below", "half").agg(F.count_if((t >= F.col("pass_below")) & (t <= 0.5)).alias("escalated"), F.count_if((t > 0.5) & toxic).alias("tp"), F.count_if((t > 0.5) & ~toxic).alias("fp"), F.count_if(toxic).alias("toxic"))


def hygiene_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """184 samples in four batches: 46 clean documents by hash rank, with a secret, personal data, insults, or nothing put in."""
    docs = labelled(spark, sf_dir).where("half = 1 and quality = 1 and toxic = 0")  # the lexicon learns from half 0
    docs = docs.where(F.size(hygiene.secret_counts(F.col("text"))) == 0).where(F.size(hygiene.pii_findings(F.col("text"))) == 0)
    few = docs.orderBy(F.md5(F.concat(F.lit("184|"), F.col("doc_id").cast("string"))), "doc_id").limit(184).select("doc_id", "text")  # the feature: a sample of 184
    from pyspark.sql import Window

    few = few.withColumn("k", F.row_number().over(Window.orderBy("doc_id")) - 1).withColumn("batch", F.element_at(F.array(*map(F.lit, ("secrets", "pii", "toxic", "clean"))), (F.col("k") % 4 + 1).cast("int")))
    planted = F.when(F.col("batch") == "secrets", F.concat(F.lit(' token = "'), F.sha1(F.col("doc_id").cast("string")), F.lit('"'))).when(F.col("batch") == "pii", F.concat(F.lit(" Mail joan"), F.col("doc_id").cast("string"), F.lit("@example.com or +1 (212) 555-0187."))).when(F.col("batch") == "toxic", " You stupid idiot, you pathetic loser.").otherwise("")
    return few.select("doc_id", "batch", F.concat("text", planted).alias("text"))


@query()
def workload_hygiene_184(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per batch and gate: rejected or changed, and how many rows each gate saw; with the clean batch as the control."""
    from refinery.records import to_records

    lexicon = hygiene.learn_lexicon(labelled(spark, sf_dir).where("half = 0").select("doc_id", "text", "toxic"))
    made = to_records(hygiene_batches(spark, sf_dir), {"output": "text", "metadata": F.create_map(F.lit("batch"), "batch")}, "language_modeling", "batches", ("doc_id",))
    out, report = hygiene.hygiene(made, lexicon, CurationConfig(secrets_gate=True, pii=True, toxicity_gate=True))
    out = out.withColumn("batch", F.col("metadata")["batch"])
    changed = F.exists("provenance_chain", lambda p: p["step"] == "pseudonymize")
    by = out.groupBy("batch").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("rejecting_step") == "secrets_gate").alias("secrets_rejected"), F.count_if(changed).alias("pii_replaced"), F.count_if(F.col("rejecting_step") == "toxicity_gate").alias("toxic_rejected"))
    return by.withColumn("specific", F.col("batch").isin("secrets", "pii", "toxic") | (F.col("secrets_rejected") + F.col("pii_replaced") + F.col("toxic_rejected") == 0))


# ---- runs -----------------------------------------------------------------------------------------------------------------------


def screened(spark: SparkSession, sf_dir: str):
    """Schema gate, exact deduplication and the secrets gate over documents."""
    return Curation(spark, CurationConfig(dedup="exact", secrets_gate=True)).run(doc_records(spark, sf_dir))


STAGES = f"""with {TOKENS}, n as (select doc_id, text, len(list_filter(string_split_regex(text, '\\s+'), lambda w: w <> '')) as n from documents), a as (select doc_id, case when trim(text) = '' then 'schema_missing' when n < 10 then 'schema_too_short' when n > 4096 then 'schema_too_long' end as bad from n),
b as (select doc_id, {KEY} as key from documents join a using (doc_id) where bad is null), x as (select doc_id, doc_id <> min(doc_id) over (partition by key) as dup from b),
s as (select doc_id, doc_id in (select doc_id from e where bits > 3.0) as secret from x where not dup)"""


@query(f"""{STAGES} select 'schema_gate' as step, count(*)::bigint as n_in, count(*) filter (bad is null)::bigint as n_accepted, count(*) filter (bad is not null)::bigint as n_rejected from a
union all select 'dedup_exact', count(*), count(*) filter (not dup), count(*) filter (dup) from x union all select 'secrets_gate', count(*), count(*) filter (not secret), count(*) filter (secret) from s""")
def run_stage_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([tuple(c[k] for k in ("step", "n_in", "n_accepted", "n_rejected")) for c in screened(spark, sf_dir).counts], "step string, n_in long, n_accepted long, n_rejected long")


@query(f"""{STAGES}, r as (select 'schema_gate' as step, bad as code from a where bad is not null union all select 'dedup_exact', 'exact_duplicate' from x where dup union all select 'secrets_gate', 'secrets' from s where secret)
select coalesce(step, 'all') as step, coalesce(code, 'all') as code, count(*)::bigint as n from r group by rollup (step, code)""")
def run_rejection_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = rejection_breakdown(screened(spark, sf_dir).table)
    return rows.select(F.coalesce("rejecting_step", F.lit("all")).alias("step"), F.coalesce("code", F.lit("all")).alias("code"), "n")


@query(f"{STAGES} select (select count(*) from documents)::bigint as rows_in, (select count(*) from s where not secret)::bigint as passed, ((select count(*) from documents) - (select count(*) from s where not secret))::bigint as rejected")
def run_conserved(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No silent drop: what came in is what passed and what was rejected."""
    table = screened(spark, sf_dir).table
    return table.agg(F.count(F.lit(1)).alias("rows_in"), F.count_if(F.col("status") == "accepted").alias("passed"), F.count_if(F.col("status") == "rejected").alias("rejected"))


@query()
def workload_clean_dedup_export(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Usage pattern 1: clean and near-deduplicate conversations and export them in two formats; the rows of each export."""
    from refinery.plans.export import lines
    from refinery.records import passed, to_records
    from refinery.sources import detect

    turns = detect.turns_of(read(spark, sf_dir, "conversations"))
    ask, out = detect.conversation_fields(F.col("turns"))
    made = to_records(turns, {"instruction": ask, "output": out, "metadata": F.create_map(F.lit("turns"), F.to_json("turns"))}, "conversational", "conversations", ("conv_id",))
    result = Curation(spark, CurationConfig(min_tokens=5, clean=True, clean_transforms=("control", "whitespace"), dedup="minhash")).run(made)
    ok = passed(result.table)  # written by the run
    return lines(ok, "alpaca").select(F.lit("alpaca").alias("format"), "id", "line").unionByName(lines(ok, "sharegpt").select(F.lit("sharegpt").alias("format"), "id", "line"))


@query()
def workload_dedup_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs found and recall against a high-recall banding, over n and the threshold."""
    texts = materialize(_normal(spark, sf_dir), "texts")
    out = None
    for n in (3, 5):
        full = materialize(dedup.near_pairs(texts, n, 0.7, bands=(16, 8)), "full")
        for t in (0.85, 0.9, 0.95):
            auto = dedup.near_pairs(texts, n, t, bands=dedup.choose_bands(128, t)).select("a", "b", F.lit(1).alias("hit"))
            row = full.where(F.col("similarity") >= t).join(auto, ["a", "b"], "left").agg(F.lit(n).alias("n"), F.lit(t).alias("threshold"), F.count(F.lit(1)).alias("pairs"), F.count("hit").alias("found"))
            out = row if out is None else out.unionByName(row)
    return out.withColumn("recall", F.when(F.col("pairs") > 0, F.col("found") / F.col("pairs")).otherwise(1.0))


@query()
def workload_dedup_policies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Survivors of the exact, greedy and component policies."""
    docs = materialize(doc_records(spark, sf_dir), "records")
    frames = {"exact": dedup.dedup_exact(docs), "greedy": dedup.dedup_minhash(docs, bands=(16, 8)), "component": dedup.dedup_minhash(docs, bands=(16, 8), policy="component")}
    out = None
    for name, df in frames.items():
        row = df.agg(F.lit(name).alias("policy"), F.count_if(F.col("status") == "accepted").alias("survivors"))
        out = row if out is None else out.unionByName(row)
    return out
