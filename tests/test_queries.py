"""Every registered query against its SQL on the smallest tables; brute force where SQL has no words for it."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from refinery.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(name, spark, sf, duck, same_rows):
    same_rows(QUERIES[name](spark, sf).toPandas(), duck.execute(ORACLES[name]).df())


def test_near_pairs_against_brute_force(spark, sf):
    import re

    got = {(r.a, r.b): r.similarity for r in QUERIES["dedup_jaccard_pairs"](spark, sf).collect()}
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    sets = {r.doc_id: (lambda t: {t[k : k + 3] for k in range(max(1, len(t) - 2))})(re.sub(r"\s+", " ", r.text.lower()).strip()) for r in docs}
    ids = sorted(sets)
    true = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for k, a in enumerate(ids) for b in ids[k + 1 :]}
    true = {k: v for k, v in true.items() if v >= 0.85}
    assert set(got) <= set(true) and len(got) >= 0.97 * len(true)
    assert all(abs(true[k] - v) < 1e-6 for k, v in got.items())


def test_diversity_gate_is_the_sequential_reference_set(spark, sf):
    got = {r.id: r.rejection_reason for r in QUERIES["gate_diversity"](spark, sf).collect()}
    rows = sorted((r.vec_id, np.array(r.embedding, dtype=np.float64)) for r in spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding").collect())
    kept: list = []
    for i, v in rows:
        v = v / np.linalg.norm(v)
        if all(v @ w <= 0.4 for _, w in kept):
            kept.append((i, v))
    assert {i for i, why in got.items() if why is None} == {i for i, _ in kept}


def test_cross_run_equals_one_run_per_order(spark, sf):
    got = {r.id: (r.run, r.rejection_reason) for r in QUERIES["dedup_cross_run_embedding"](spark, sf).collect()}
    rows = sorted((r.vec_id % 2, r.vec_id, np.array(r.embedding, dtype=np.float64)) for r in spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding").collect())
    kept: list = []
    for run, i, v in rows:
        v = v / np.linalg.norm(v)
        mine = [w for r, w in kept if r == run]
        seen = any(v @ w > 0.4 for r, w in kept if r < run)
        ok = not seen and all(v @ w <= 0.4 for w in mine)
        assert (got[i][1] is None) == ok
        if ok:
            kept.append((run, v))


def test_adaptive_beats_naive_and_costs_at_most_five(spark, sf):
    """With the easing that the simulator has built in; the control is below."""
    rows = {r.type: r for r in QUERIES["measure_recall_gap"](spark, sf).collect()}
    assert set(rows) == {"overall", "contradicts_source", "parametric_drift", "domain_mismatch", "instruction_quality"}
    assert rows["overall"].adaptive > rows["overall"].naive
    modes = {r["mode"]: r for r in QUERIES["recover_probe_modes"](spark, sf).collect()}
    assert modes[None].calls <= 5 * modes[None].n


def test_without_easing_the_gap_is_noise(spark, sf):
    rows = {r.easing: r for r in QUERIES["measure_easing_control"](spark, sf).collect()}
    assert abs(rows[0.0].gap_points) <= 12 and rows[1.0].gap_points > rows[0.0].gap_points


def test_a_full_run_recovers_and_diagnoses(spark, sf):
    rows = QUERIES["workload_full_run"](spark, sf).collect()
    steps, modes = [r for r in rows if r.part == "step"], {r.name: r for r in rows if r.part == "mode"}
    assert [r.name for r in steps] == ["schema_gate", "dedup_exact", "secrets_gate", "pseudonymize", "toxicity_gate", "generate_adversarial_qa", "grounding_gate", "reward_gate", "diversity_gate"]
    assert all(r.n_in == r.n_accepted + r.n_rejected for r in steps) and all(b.n_in == a.n_accepted for a, b in zip(steps, steps[1:]) if not b.name.startswith("generate"))
    assert sum(m.n_accepted for m in modes.values()) > 0 and set(modes) <= {"threshold_marginal", "generator_temperature", "generator_parametric", "instruction_quality", "response_quality", "domain_mismatch", "source_ambiguous", "near_duplicate", "unknown"}


TASK_KINDS = {"qa": "instruction_following", "adversarial_qa": "instruction_following", "preference": "preference", "grpo": "grpo", "multiturn": "conversational", "evol": "instruction_following", "cot": "instruction_following", "inject": "instruction_following"}


@pytest.mark.parametrize("task", sorted(TASK_KINDS))
def test_every_task_runs(task, spark, sf):
    from refinery.config import CurationConfig
    from refinery.plans.run import Curation
    from refinery.queries.base import doc_records

    docs = doc_records(spark, sf).limit(25).withColumn("id", F.col("id").cast("string"))
    cfg = CurationConfig(task=task, chunk_strategy="fixed", chunk_max_tokens=120, chunk_overlap_tokens=10, extract_tables=True, num_questions=2, difficulty="hard", score_responses=True, num_responses=3, evolve_strategies=("deepen",), evolve_answer=True, num_turns=2, inject_rate=0.5)
    rows = Curation(spark, cfg).run(docs).passed.collect()
    assert rows and {r.task_type for r in rows} == {TASK_KINDS[task]} and all(r.input and r.provenance_chain[-1].step == f"generate_{task}" for r in rows)
    if task == "grpo":
        assert all(len(r.responses) == len(r.reward_scores) == 3 for r in rows)


def scripted_backend(answer):
    from refinery.operators.generation import Backend

    class Scripted(Backend):
        model = "scripted"

        def generate(self, prompt, temperature):
            return {"text": answer(prompt, temperature), "model": self.model, "prompt_tokens": len(prompt.split()), "completion_tokens": 1, "latency": 0.0}

    return Scripted()


ANSWERED = {
    "qa": '[{"question": "What?", "answer": "This."}]', "adversarial_qa": 'Sure: [{"question": "What?", "answer": "This."}]', "preference": '{"question": "What?", "chosen": "This.", "rejected": "That."}', "grpo": "This.", "evol": "What, and why?", "cot": "First this, then that.",
    "multiturn": '[{"role": "user", "content": "What?"}, {"role": "assistant", "content": "This."}]',
}


@pytest.mark.parametrize("task", sorted(ANSWERED))
def test_tasks_over_a_backend(task, spark, tmp_path):
    """Each task through a backend and the ledger; answers that can't be read end as rejected records with the raw answer in their chain."""
    from refinery.config import CurationConfig
    from refinery.plans.run import Curation
    from refinery.records import to_records

    texts = [(k, " ".join(f"w{k}_{i}" for i in range(20)) + ("." if k else " unreadable.")) for k in range(4)]
    records = to_records(spark.createDataFrame(texts, "k long, t string"), {"output": "t"}, "language_modeling", "t", ("k",))
    answer = ANSWERED[task]
    backend = scripted_backend(lambda prompt, t: "" if "unreadable" in prompt else answer)
    cfg = CurationConfig(task=task, chunk_strategy="paragraph", num_questions=1, preference_mode="single_call", dialogue_mode="single_call", num_responses=2, evolve_strategies=("deepen",), ledger_dir=str(tmp_path / "ledger"), output_dir=str(tmp_path / "out"), parse_retries=1)
    result = Curation(spark, cfg, {"generator_backend": backend}).run(records)
    good, bad = result.passed.collect(), [r for r in result.rejected.collect() if r.rejection_reason == "generation_parse_failed"]
    assert len(good) == 3 and len(bad) == 1 and "raw_response" in bad[0].provenance_chain[-1].notes and bad[0].rejecting_step == f"generate_{task}"
    assert all(r.task_type == TASK_KINDS[task] and "call" in r.provenance_chain[-1].notes for r in good)
    assert result.manifest["tokens"]["scripted"]["calls"] >= 5 and result.manifest["tokens"]["scripted"]["prompt_tokens"] > 0
    with pytest.raises(ValueError, match="call_budget"):
        Curation(spark, cfg.patch({"ledger_dir": str(tmp_path / "other"), "call_budget": 2}), {"generator_backend": backend}).run(records)


def test_two_pass_and_turn_by_turn_over_a_backend(spark, tmp_path):
    from refinery.config import CurationConfig
    from refinery.plans.run import Curation
    from refinery.records import to_records

    records = to_records(spark.createDataFrame([(1, " ".join(f"w{i}" for i in range(20)) + ".")], "k long, t string"), {"output": "t"}, "language_modeling", "t", ("k",))
    pair = scripted_backend(lambda prompt, t: "Poor." if t > 1 else '{"question": "What?", "chosen": "This.", "rejected": "x"}')
    base = {"chunk_strategy": "paragraph", "ledger_dir": str(tmp_path / "ledger")}
    row = Curation(spark, CurationConfig(task="preference", **base), {"generator_backend": pair}).run(records).passed.first()
    assert (row.chosen, row.rejected) == ("This.", "Poor.")
    talk = scripted_backend(lambda prompt, t: f"said {prompt.count('user:') + prompt.count('assistant:')}")
    row = Curation(spark, CurationConfig(task="multiturn", num_turns=2, **base), {"generator_backend": talk}).run(records).passed.first()
    assert [t["content"] for t in __import__("json").loads(row.metadata["turns"])] == ["said 0", "said 1", "said 2", "said 3"]


def test_judges_and_probes_over_a_backend(spark, tmp_path):
    """A separate judge behind a backend decides both gates; the probe's strict prompt repairs what it fails; the rewrite follows the judge's weakest dimension."""
    from refinery.config import CurationConfig
    from refinery.plans.run import Curation
    from refinery.records import to_records

    rows = [(1, "Q one?", "good answer", "The source."), (2, "Q two?", "bad answer", "The source."), (3, "Q three?", "weak answer", "The source.")]
    records = to_records(spark.createDataFrame(rows, "k long, q string, a string, s string"), {"instruction": "q", "output": "a", "input": "s"}, "instruction_following", "t", ("k",))

    def judge(prompt, t):
        if prompt.startswith("Score"):
            return '{"scores": {"depth": %s}, "overall": 0.9, "weaknesses": "thin"}' % ("0.1" if "weak answer" in prompt else "0.9")
        return '{"score": %s, "supported": [], "unsupported": []}' % ("0.2" if "bad" in prompt else "0.9")

    generator = scripted_backend(lambda prompt, t: "rewritten" if prompt.startswith("Rewrite") else "good new answer" if "only statements" in prompt else "bad again")
    cfg = CurationConfig(schema_gate=False, gates=("grounding", "reward"), recovery="adaptive", refiner=True, reward_dimensions=("depth",), judge_model="scripted", ledger_dir=str(tmp_path / "ledger"), output_dir=str(tmp_path / "out"))
    result = Curation(spark, cfg, {"generator_backend": generator, "judge_backend": scripted_backend(judge)}).run(records)
    got = {r.instruction: r for r in result.table.collect()}
    assert got["Q one?"].status == "accepted" and got["Q two?"].output == "good new answer" and got["Q two?"].status == "accepted"
    assert result.diagnostics.modes["generator_parametric"] == {"n": 1, "recovered": 1, "calls": 1} and result.diagnostics.modes["response_quality"]["n"] == 1
    notes = {p.step: p.notes for p in got["Q two?"].provenance_chain}
    assert notes["recover_adaptive"]["mode"] == "generator_parametric" and (tmp_path / "out" / "diagnostic_summary.json").exists()


def test_custom_gates_and_layout_documents(spark, tmp_path):
    from refinery.config import CurationConfig
    from refinery.operators import gates
    from refinery.plans.run import Curation
    from refinery.records import reject
    from refinery.sources.readers import SourceSpec

    (tmp_path / "a.html").write_text("<h1>One</h1><p>" + "alpha beta gamma delta epsilon zeta. " * 4 + "</p><h2>Two</h2><p>" + "eta theta iota kappa lambda mu. " * 4 + "</p>")
    gates.register_gate("short", lambda df, cfg, ctx: reject(df, F.length("output") < 145, "schema_too_short", "short"))
    try:
        spec = SourceSpec("documents", str(tmp_path / "*.html"), {"extractor": lambda b: b.decode().replace("<h1>", "# ").replace("<h2>", "\n# ").replace("</h1><p>", "\n").replace("</h2><p>", "\n").replace("</p>", "")}, mapping={"output": "text"}, task_type="language_modeling")
        made = Curation(spark, CurationConfig(sources=(spec,), gates=("short",), min_tokens=1)).run()
        assert [r.metadata["heading"] for r in made.passed.orderBy("output").collect()] == ["One"] and made.rejected.count() == 1
        asked = Curation(spark, CurationConfig(sources=(spec,), pdf_output_mode="qa", min_tokens=1)).run().passed.collect()
        assert asked and all(r.instruction.endswith("?") and r.input for r in asked)
    finally:
        gates.CUSTOM_GATES.clear()


def test_hygiene_batches(spark):
    """On tables with enough labels for a lexicon of one half and 184 samples of the other."""
    rows = {r.batch: r for r in QUERIES["workload_hygiene_184"](spark, "/root/testdata/sf0.01").collect()}
    assert rows["secrets"].secrets_rejected == rows["secrets"].n
    assert rows["pii"].pii_replaced == rows["pii"].n
    assert rows["toxic"].toxic_rejected > 0.9 * rows["toxic"].n
    assert rows["clean"].specific


def test_small_functions(spark):
    from pyspark.sql import functions as F

    from refinery.functions import text as tx
    from refinery.operators import hygiene

    df = spark.createDataFrame([("aabb", "4539578763621486", "GB82WEST12345698765432", "the cat sat", "the cat ran")], "e string, c string, i string, h string, r string")
    got = df.select(tx.shannon_entropy(F.col("e")), tx.luhn(F.col("c")), hygiene.iban_valid(F.col("i")), tx.rouge_l(F.col("h"), F.col("r")), tx.shannon_entropy(F.lit(None).cast("string"))).first()
    assert got[0] == 1.0 and got[1] and got[2] and abs(got[3] - 2 / 3) < 1e-9 and got[4] is None


def test_pseudonyms_are_consistent_within_and_differ_between_records(spark):
    from pyspark.sql import functions as F

    from refinery.operators.hygiene import pseudonymize
    from refinery.records import to_records

    df = spark.createDataFrame([(1, "a@b.com wrote", "to a@b.com and c@d.org"), (2, "a@b.com wrote", "x")], "k int, i string, o string")
    rows = pseudonymize(to_records(df, {"instruction": "i", "output": "o"}, "instruction_following", "t", ("k",)).orderBy("source_uri")).select("instruction", "output", F.to_json("provenance_chain").alias("p")).collect()
    by = {r.output != "x": r for r in rows}
    first = by[True].instruction.split()[0]
    assert first in by[True].output and "a@b.com" not in by[True].instruction + by[True].output + by[True].p
    assert by[False].instruction.split()[0] != first
    assert len({w for w in by[True].output.split() if "@" in w}) == 2


def test_ledger_pays_once(spark, tmp_path):
    from pyspark.sql import functions as F

    from refinery.operators.generation import LEDGER, Backend, GenerationTask, run_task

    class Echo(Backend):
        model = "echo"

        def generate(self, prompt, temperature):
            return {"text": prompt.upper(), "model": self.model, "prompt_tokens": 1, "completion_tokens": 1, "latency": 0.0}

    df = spark.createDataFrame([("a",), ("b",), ("a",)], "t string")
    task = GenerationTask(lambda: F.col("t"), lambda c: F.when(c != "B", c))
    for _ in range(2):
        got = run_task(df, task, Echo(), str(tmp_path / "ledger"), parse_retries=1).collect()
    assert sorted((r.t, r.generated, r.raw_response) for r in got) == [("a", "A", "A"), ("a", "A", "A"), ("b", None, "B")]
    assert spark.read.schema(LEDGER).parquet(str(tmp_path / "ledger")).count() == 3


def test_a_run_writes_its_four_artefacts_and_drops_nothing(spark, sf, tmp_path):
    import json

    from refinery.config import CurationConfig
    from refinery.plans.run import Curation
    from refinery.sources.readers import SourceSpec

    out = str(tmp_path / "out")
    cfg = CurationConfig(sources=(SourceSpec("parquet", f"{sf}/documents.parquet"),), secrets_gate=True, dedup="exact", output_dir=out, export_formats=("corpus",), output_split={"train": 0.9, "test": 0.1})
    result = Curation(spark, cfg).run()
    n = spark.read.parquet(f"{sf}/documents.parquet").count()
    assert result.passed.count() + result.rejected.count() == n == result.table.count()
    manifest = json.loads((tmp_path / "out" / "manifest.json").read_text())
    assert manifest["config_hash"] == cfg.digest() and manifest["exports"]["corpus"]["written"] == result.passed.count()
    assert (tmp_path / "out" / "card.md").exists() and spark.read.json(f"{out}/rejected").count() == result.rejected.count()
    assert (tmp_path / "out.sha256").exists() and "passed" in result.summary()
    assert sorted(p.name for p in (tmp_path / "out/data/corpus").iterdir() if p.is_dir()) == ["split=test", "split=train"]


def test_empty_tables(spark, sf, tmp_path):
    for t in ("documents", "embeddings", "benchmark", "labels"):
        spark.read.parquet(f"{sf}/{t}.parquet").limit(0).write.parquet(str(tmp_path / f"{t}.parquet"))
    for name in ("dedup_exact", "sample_stratified", "hygiene_secrets", "hygiene_pii_hits", "gen_qa_extractive", "dedup_contamination"):
        QUERIES[name](spark, str(tmp_path)).collect()


def test_the_rest_stands_without_the_llm_subpackage():
    import pathlib
    import subprocess
    import sys

    root = pathlib.Path(__file__).resolve().parent.parent
    code = "import sys; sys.modules['refinery.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; q = e.queries(); assert 'run_stage_counts' in q and not any(k.startswith('op1_') for k in q)"
    assert subprocess.run([sys.executable, "-c", code], cwd=root).returncode == 0


def test_exact_vector_pairs_at_any_size(spark, tmp_path, monkeypatch):
    """Beyond the bound of `auto` too."""
    monkeypatch.setattr("refinery.operators.dedup.EXACT_VECTORS", 10)
    m = np.random.default_rng(3).standard_normal((1200, 8)).astype(np.float32)
    spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(m)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    u = m.astype(np.float64) / np.linalg.norm(m.astype(np.float64), axis=1, keepdims=True)
    x, y = np.nonzero(np.triu(u @ u.T > 0.4, 1))
    assert QUERIES["dedup_embedding_exact"](spark, str(tmp_path)).select("a", "b").toPandas().sort_values(["a", "b"]).values.tolist() == np.stack((x, y), 1).tolist()


def test_planted_secrets_whatever_the_id(spark, tmp_path):
    """The md5 of these ids holds 3.0 bits a digit at most."""
    spark.createDataFrame([(i,) for i in (46437, 67453, 198189)], "doc_id long").write.parquet(f"{tmp_path}/documents.parquet")
    assert [tuple(r) for r in QUERIES["hygiene_secrets_planted"](spark, str(tmp_path)).collect()] == [(5, "hex_entropy", 3)]


def test_sources_of_folders_are_named_by_their_table(spark, sf, tmp_path):
    for t in ("documents", "benchmark"):
        spark.read.parquet(f"{sf}/{t}.parquet").repartition(3).write.parquet(f"{tmp_path}/{t}.parquet")
    count = lambda folder: {r["source"]: r.n for r in QUERIES["ingest_multi_source"](spark, folder).collect()}
    assert count(str(tmp_path)) == count(sf) and set(count(sf)) == {"documents", "benchmark"}


@pytest.mark.parametrize("part", [128, 4])
def test_pairs_are_verified_in_blocks_of_texts(spark, monkeypatch, part):
    """Components whole or in parts: the pairs and similarities of brute force, each once; equal texts are pairs as well."""
    import random

    from refinery.operators import dedup

    monkeypatch.setattr(dedup, "PART", part)
    rng, texts = random.Random(2), {}
    for i in range(40):
        base = f"{'abcd'[i % 4]} quick brown fox jumps over the lazy dog near the river bank and runs {i % 4} " * 3
        texts[i] = base if i % 5 == 0 else base + "".join(rng.choice("klmnop") for _ in range(rng.randrange(1, 20)))
    rows = dedup.near_pairs(spark.createDataFrame(list(texts.items()), "id long, text string"), 3, 0.85, bands=(32, 4)).collect()
    sets = {i: {t[k : k + 3] for k in range(len(t) - 2)} for i, t in texts.items()}
    want = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a in texts for b in texts if a < b}
    want = {k: v for k, v in want.items() if v >= 0.85}
    got = {(r.a, r.b): r.similarity for r in rows}
    assert len(got) == len(rows) and set(got) <= set(want) and len(got) >= 0.99 * len(want)
    assert all(abs(want[k] - v) < 1e-9 for k, v in got.items())
    assert all((a, b) in got for a in texts for b in texts if a < b and texts[a] == texts[b])


def test_arrow_scores_equal_their_column_forms(spark, sf):
    """Grounding against the claims' mean support on the JVM; the common subsequence against the plain table; the judge is no fold of the JVM any more."""
    from refinery.functions import scores
    from refinery.operators import gates
    from refinery.queries.generate import qa

    rows = qa(spark, sf).limit(300).select("input", F.concat("output", F.lit("\nIt is NOT so.  Its 17 parts\tdo Nicht.")).alias("a"))
    odd = spark.createDataFrame([("", ""), (None, "One."), ("One two.", None), ("no 4 or 5 of it, ever. Ja!", "no 4 of it, ever. 6"), ("a b", "a b c d"), ("É x ΟΔΟΣ", "É x ΟΔΟΣ. x")], "input string, a string")
    rows = rows.unionByName(odd)
    scored = rows.select(gates.grounding_score(F.col("a"), F.col("input")).alias("x"), gates._mean_support(gates.claim_scores(F.col("a"), F.coalesce("input", F.lit("")))).alias("y"))
    assert all(r.x == r.y for r in scored.collect())
    assert "ArrowEvalPython" in scored._jdf.queryExecution().executedPlan().toString()
    rng = np.random.default_rng(3)
    for _ in range(200):
        a, b = (rng.integers(0, 4, rng.integers(0, 12)).tolist() for _ in range(2))
        table = np.zeros((len(a) + 1, len(b) + 1), int)
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1, j + 1] = table[i, j] + 1 if x == y else max(table[i, j + 1], table[i + 1, j])
        assert scores.common_subsequence(a, b) == table[-1, -1]


@pytest.mark.parametrize("arm", ["diagnose", "retry"])
def test_one_pass_probes_as_the_waves_do(spark, sf, arm):
    from refinery.functions import text as tx
    from refinery.operators import recovery
    from refinery.queries.generate import qa, scripted

    rows = qa(spark, sf).withColumn("grounding_score", tx.hash_unit(F.lit("split"), F.col("qa_id")))
    found = [getattr(recovery, arm)(rows, scripted, judge=lambda answer, source: answer.cast("double"), one_pass=one) for one in (False, True)]
    waves, once = ([tuple(r) for r in x.select("qa_id", "mode", "calls", "recovered", "final_answer", "final_asked").orderBy("qa_id").collect()] for x in found)
    assert len(waves) > 100 and waves == once


def test_measures_leave_no_wide_tables(spark, sf):
    """The samples of one profile make room for the next; what stays is the pairs and the measures' rows."""
    import os
    from urllib.parse import urlparse

    from refinery.operators.storage import shared_dir

    at = urlparse(shared_dir(spark)).path
    before = set(os.listdir(at)) if os.path.isdir(at) else set()
    assert QUERIES["measure_gate_overlap"](spark, sf).count() == 3
    kinds = {x.split("-")[1] for x in set(os.listdir(at)) - before}
    assert "pairs" in kinds and not kinds & {"experiment", "qa"}


def test_recovery_rate_scores_each_answer_once(spark, sf, monkeypatch):
    """The same counts as from samples and probes written out as texts, for a profile; and each pair's answers are scored in one call."""
    from refinery.operators import gates, generation
    from refinery.queries import generate

    rows, _ = generate.experiment(generate.references(spark, sf), "medium")
    wanted = {}
    for arm in ("adaptive", "naive"):
        r = generate.probed(rows, "medium", arm).agg(F.count(F.lit(1)), F.count_if("recovered"), F.sum("calls"), F.max("calls")).first()
        wanted[arm] = tuple(r)
    calls = []
    monkeypatch.setattr(gates, "grounding_scores", lambda answers, source, real=gates.grounding_scores: calls.append(len(answers)) or real(answers, source))
    got = {r.arm: (r.rejected, r.recovered, r.calls, r.most_calls) for r in QUERIES["measure_recovery_rate"](spark, sf).collect() if r.profile == "medium"}
    assert got == wanted and calls == [len(generation.FAULTS) - 1 + len(generation.PROFILES)]


@pytest.mark.parametrize("name", ["dedup_choose_bands", "recover_taxonomy"])
def test_rows_come_from_the_documents(spark, sf, tmp_path, name):
    """Half of the documents give other counts: the query reads the table."""
    spark.read.parquet(f"{sf}/documents.parquet").where("doc_id % 2 = 0").write.parquet(str(tmp_path / "documents.parquet"))
    whole, half = (QUERIES[name](spark, at).collect() for at in (sf, str(tmp_path)))
    count = lambda rows: sum(r["documents" if name == "dedup_choose_bands" else "n"] for r in rows)
    assert count(whole) > count(half) > 0
    if name == "dedup_choose_bands":
        assert count(whole) == spark.read.parquet(f"{sf}/documents.parquet").count() and len(whole) > 1


def test_capabilities_are_shown_on_documents(spark, sf, tmp_path):
    """the criteria were looked up in the package alone, and no table was read. A copy without any duplicate has other counts."""
    spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 3").write.parquet(str(tmp_path / "documents.parquet"))
    seen = lambda at: {r.k: r.n for r in QUERIES["measure_capabilities"](spark, at).collect() if r.n is not None}
    few, all_ = seen(str(tmp_path)), seen(sf)
    assert few[1] == spark.read.parquet(str(tmp_path / "documents.parquet")).count() < all_[1] == 200
    assert set(all_) == {1, 3, 7, 9} and all_[3] + all_[7] <= all_[9] <= 200


def test_quality_is_taken_over_all_pairs(spark, sf, monkeypatch):
    """the metrics came from a quarter of the pairs."""
    from refinery.operators import generation
    from refinery.queries.generate import experiment, references

    monkeypatch.setattr(generation, "PROFILES", {"small": generation.PROFILES["small"]})
    got = {r.metric: r for r in QUERIES["measure_quality"](spark, sf).collect()}
    rows, _ = experiment(references(spark, sf), "small")
    both = (F.col("grounding_score") >= 0.7) & (F.col("reward_score") >= 0.7)
    want = rows.agg(F.avg("grounding_score").alias("base"), F.avg(F.when(both, F.col("grounding_score"))).alias("other")).first()
    assert set(got) == {"rouge_l", "match_f1", "faithfulness"}
    assert abs(got["faithfulness"].base - want.base) < 1e-9 and abs(got["faithfulness"].other - want.other) < 1e-9


def test_exported_conversations_are_cleaned(spark, tmp_path):
    """cleaning left the turns alone that the conversation export writes."""
    import json

    ask, answer = "what  is\x07 the \t capital of this country", "it\x01 is  a   town  by the river"
    rows = [(1, 0, "user", ask), (1, 1, "assistant", "let   me\x1f see"), (1, 2, "user", "and   then"), (1, 3, "assistant", answer), (2, 0, "user", "is this one clean already or not"), (2, 1, "assistant", "it is as it was")]
    spark.createDataFrame(rows, "conv_id long, turn int, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    lines = [(r.format, json.loads(r.line)) for r in QUERIES["workload_clean_dedup_export"](spark, str(tmp_path)).collect()]
    talks = sorted(([t["value"] for t in r["conversations"]] for f, r in lines if f == "sharegpt"), key=len)
    assert talks[0] == ["is this one clean already or not", "it is as it was"]
    assert talks[1] == ["what is the capital of this country", "let me see", "and then", "it is a town by the river"]
    assert ("what is the capital of this country", "it is a town by the river") in {(r["instruction"], r["output"]) for f, r in lines if f == "alpaca"}


def test_turns_in_metadata_take_every_transform(spark):
    """F11, the transforms that run in Python too; roles, other metadata and turns that need nothing stay."""
    import json

    from refinery.operators.clean import clean
    from refinery.records import to_records

    turns = [{"role": "user", "content": "<b>été</b>  &lt;now&gt;"}, {"role": "assistant", "content": "cafÃ©"}, {"role": "assistant"}]
    raw = spark.createDataFrame([(1, json.dumps(turns)), (2, '[{"role": "user",  "content": "plain"}]'), (3, "no turns")], "k int, t string")
    made = to_records(raw, {"output": F.lit("x"), "metadata": F.create_map(F.lit("turns"), F.col("t"), F.lit("k"), F.col("k").cast("string"))}, "conversational", "s", ("k",))
    got = {r.metadata["k"]: r for r in clean(made).collect()}
    assert [(t["role"], t.get("content")) for t in json.loads(got["1"].metadata["turns"])] == [("user", "été <now>"), ("assistant", "café"), ("assistant", None)]
    assert got["2"].metadata["turns"] == '[{"role": "user",  "content": "plain"}]' and got["3"].metadata["turns"] == "no turns"
    assert len(got["1"].provenance_chain) == 5


def test_easing_control_scores_each_answer_once(spark, sf, monkeypatch):
    """each share and arm wrote and scored its answers anew. One call now scores them all, of all damaged pairs; the counts are those of probes over texts."""
    from refinery.operators import gates, generation
    from refinery.queries import generate

    rows, truth = generate.experiment(generate.references(spark, sf), "small")
    hurt = truth.where("injected_type is not null").select("qa_id")
    want = generate.probed(rows, "small", "adaptive", generation.eased(0.5)).join(hurt, "qa_id", "left_semi").agg(F.count_if("recovered").alias("r"), F.sum("calls").alias("c")).first()
    calls = []
    monkeypatch.setattr(gates, "grounding_scores", lambda answers, source, real=gates.grounding_scores: calls.append(len(answers)) or real(answers, source))
    got = {r.easing: r for r in QUERIES["measure_easing_control"](spark, sf).collect()}
    assert calls == [len(generation.FAULTS)]  # a faulty question keeps its answer; the damaged sample is one more
    assert got[0.5].injected == hurt.count() and got[0.5].adaptive_calls == want.c and abs(got[0.5].adaptive - 100.0 * want.r / got[0.5].injected) < 1e-9
