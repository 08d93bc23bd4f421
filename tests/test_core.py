"""Configuration, records, planning, banding: mostly without jobs."""

import dataclasses
import itertools

import pytest

from refinery.config import CurationConfig, load
from refinery.operators.dedup import band_curve, choose_bands, gram_codes
from refinery.operators.generation import PromptTemplate
from refinery.plans.run import build, explain


def test_config_patch_keeps_the_original_and_names_unknown_fields():
    a = CurationConfig()
    b = a.patch({"min_tokens": 3})
    assert (a.min_tokens, b.min_tokens) == (10, 3)
    assert a.digest() != b.digest() and a.digest() == CurationConfig(api_key="k").digest()
    with pytest.raises(ValueError, match="no_such"):
        a.patch({"no_such": 1})
    assert len(dataclasses.fields(CurationConfig)) > 100
    with pytest.raises(dataclasses.FrozenInstanceError):
        a.min_tokens = 1


def test_config_refuses_bad_values_and_warns_of_idle_limits():
    for bad in ({"dedup": "x"}, {"grounding_threshold": 2.0}, {"min_tokens": 9, "max_tokens": 3}, {"tokenizer": "bpe"}, {"gates": ("x",)}, {"output_split": {"a": 0.5}}):
        with pytest.raises(ValueError):
            CurationConfig(**bad)
    assert CurationConfig(secrets_hex_limit=4.5).warnings() and not CurationConfig().warnings()


def test_yaml_sections_and_order_of_steps(tmp_path):
    p = tmp_path / "s.yaml"
    p.write_text("gates: [reward, grounding]\ntoxicity:\n  toxicity_gate: true\nprivacy:\n  pii: true\nsecrets_gate: true\ndedup: minhash\nmax_samples: 5\npresets: [sensitive]\n")
    cfg = load(str(p))
    names = [s.name for s in build(cfg)]
    assert names == ["schema_gate", "dedup_exact", "dedup_minhash", "secrets_gate", "pseudonymize", "toxicity_gate", "grounding_gate", "reward_gate", "truncate"]
    assert cfg.toxicity_pass == 0.2 and "1. schema_gate" in explain(cfg)
    p.write_text("nonsense: 1\n")
    with pytest.raises(ValueError):
        load(str(p))


def test_bands_published_analysis():
    assert [choose_bands(128, t) for t in (0.7, 0.8, 0.85, 0.9)] == [(14, 9), (9, 13), (8, 16), (5, 25)]
    assert abs(band_curve(0.85, 8, 16) - 0.461) < 0.01 and band_curve(0.95, 8, 16) > 0.98


def test_templates_are_checked_when_made():
    with pytest.raises(ValueError, match="question"):
        PromptTemplate("{source}", ("source", "question"))


def test_gram_codes_are_exact():
    t = "abcab"
    assert len(gram_codes(t, 3)) == len({t[k : k + 3] for k in range(3)})
    assert len(gram_codes("", 3)) == 1 and len(gram_codes("ab", 3)) == 1


def test_dry_run_needs_no_session(tmp_path, capsys):
    from refinery.cli import main

    p = tmp_path / "s.yaml"
    p.write_text("secrets_gate: true\nsecrets_hex_limit: 4.5\n")
    assert main(["run", str(p), "--dry-run"]) == 0
    said = capsys.readouterr().out
    assert "secrets_gate" in said and "hex detection is off" in said


def sequential(n, edges):
    near = {i: set() for i in range(n)}
    for a, b in edges:
        near[a].add(b)
        near[b].add(a)
    kept = []
    for i in range(n):
        if not near[i] & set(kept):
            kept.append(i)
    return set(kept)


def test_first_independent_set_is_the_sequential_one(spark):
    import random

    from refinery.operators.graph import components, first_independent_set

    random.seed(4)
    edges = [tuple(random.sample(range(30), 2)) for _ in range(40)]
    df = spark.createDataFrame(edges, "a long, b long")
    got = first_independent_set(df).collect()
    touched = set(itertools.chain(*edges))
    assert {r.node for r in got if r.kept} == sequential(30, edges) & touched
    assert {r.node for r in got} == touched
    up = list(range(30))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    assert {r.node: r.label for r in components(df).collect()} == {x: root(x) for x in touched}
    assert components(df.limit(0)).count() == 0


def test_runs_find_pairs_at_the_threshold(spark):
    """The default banding, on pairs of a similarity of 0.85 to 0.9."""
    import random

    from refinery.operators.dedup import near_pairs

    rng, rows, alike = random.Random(8), [], 0
    for k in range(150):
        text = "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(400))
        other = text[:372] + "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(28))
        a, b = (set(gram_codes(t, 3).tolist()) for t in (text, other))
        alike += len(a & b) >= 0.85 * len(a | b)
        rows += [(2 * k, text), (2 * k + 1, other)]
    found = near_pairs(spark.createDataFrame(rows, "id long, text string")).count()
    assert alike >= 100 and found >= 0.97 * alike


def test_every_setting_is_read():
    import pathlib
    import re

    root = pathlib.Path(__file__).resolve().parent.parent / "refinery"
    code = "".join(f.read_text() for f in root.rglob("*.py") if f.name != "config.py" and f.parent.name != "llm")
    assert [f.name for f in dataclasses.fields(CurationConfig) if not re.search(rf"cfg\.{f.name}\b", code)] == []


def test_settings_of_tasks_and_recovery_are_checked():
    for odd in ({"task": "no_such"}, {"encoder": "no_such"}, {"inject_types": ("x",)}, {"probe_on": ("diversity",)}, {"recovery": "adaptive", "probe_max_calls": 3}, {"prompt_templates": {"qa": "no placeholder"}}, {"prompt_templates": {"x": ""}}, {"reward_prompt": "none"}, {"chunk_overlap_tokens": 512}):
        with pytest.raises(ValueError):
            CurationConfig(**odd)
    assert [x.name for x in build(CurationConfig(task="grpo", gates=("grounding",), recovery="adaptive"))][-2:] == ["generate_grpo", "grounding_gate"]


def test_a_model_needs_an_endpoint():
    from refinery.operators.tasks import backend_of

    assert backend_of(CurationConfig(), "generator", {}) is None and backend_of(CurationConfig(), "judge", {}) is None
    with pytest.raises(ValueError, match="api_base"):
        backend_of(CurationConfig(judge_model="m"), "judge", {})
    b = backend_of(CurationConfig(generator_model="m", api_base="http://localhost:1/v1", max_retries=7), "generator", {})
    assert (b.model, b.retries) == ("m", 7)


def test_the_injector_writes_no_phrase_of_its_own():
    """What damages and the simulator put in comes from the tables: their code holds no text but names of kinds, prompts and columns."""
    import ast
    import inspect

    from refinery.operators import gates, generation, recovery

    def texts(f):
        tree = ast.parse(inspect.getsource(f))
        docs = {ast.get_docstring(n, clean=False) for n in ast.walk(tree) if isinstance(n, ast.FunctionDef)}
        return {n.value for n in ast.walk(tree) if isinstance(n, ast.Constant) and isinstance(n.value, str)} - docs

    injected = set().union(*(texts(f) for f in (generation.damaged, generation.inject, generation.simulate, generation.other_source)))
    assert not [t for t in injected if " " in t.strip()]
    judged = set().union(*(texts(f) for f in (gates.claim_scores, gates.dimension_scores, recovery._try, recovery.refine)))
    assert not [t for t in judged if " " in t.strip() and len(t) > 12]


def word_texts(n=240, size=120, shared=96, seed=3):
    """Texts of random words of which a good half is common to all, some of them edited in one place: buckets hold many pairs, few of which are near."""
    import random

    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(r.randint(3, 8)))
    common = [word() for _ in range(size)]
    texts = []
    for k in range(n):
        w = list(texts[-1]) if k % 12 == 11 else [c if j < shared else word() for j, c in enumerate(common)]
        if k % 12 == 11:
            w[r.randrange(size)] = word()
        texts.append(w)
    return [" ".join(w) for w in texts]


def test_buckets_list_no_pair_that_their_parities_rule_out(spark, monkeypatch):
    """all pairs of a bucket were listed by their ids and shuffled, whatever they had in common."""
    import numpy as np

    from refinery.operators import dedup

    texts, asked = word_texts(), []
    grams = [set(gram_codes(t, 3).tolist()) for t in texts]
    alike = lambda a, b: len(grams[a] & grams[b]) / len(grams[a] | grams[b])
    near = {(a, b) for a, b in itertools.combinations(range(len(texts)), 2) if alike(a, b) >= 0.85}
    plain = dedup.verified
    monkeypatch.setattr(dedup, "verified", lambda pairs, *more: (asked.append(pairs.count()), plain(pairs, *more))[1])
    df = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    got = {(r.a, r.b) for r in dedup.near_pairs(df, 3, 0.85, bands=(64, 2)).collect()}
    assert got == near and len(near) >= 15
    assert asked[0] < 10 * len(near) < len(texts) * (len(texts) - 1) // 2 / 10  # before: nearly all pairs
    # blocks of a wide bucket, and pairs that aren't verified: all are listed
    signed = dedup.signatures(df, 3, 128, 64, 2)
    every = lambda wide, prune: {(r.a, r.b) for r in dedup.candidate_pairs(signed, wide, 0.85, prune).collect()}
    assert near <= every(7, True) == every(10**6, True) < every(7, False) == every(10**6, False)
    for a, b in ((0, 11), (3, 40), (10, 11)):
        x, y = (np.frombuffer(dedup.parity(gram_codes(texts[k], 3)), np.uint8) for k in (a, b))
        assert len(x) != len(y) or np.bitwise_count(x ^ y).sum() <= len(grams[a] ^ grams[b])


def test_parities_of_other_lengths_are_folded():
    import numpy as np

    from refinery.operators import dedup

    r = np.random.default_rng(1)
    pool = np.unique(r.integers(0, 2**62, 1200, dtype=np.uint64))
    sets = [pool[:k] for k in (500, 510, 515, 560, 1000, 1030, 1100, 1024)] + [np.sort(r.choice(pool, k, replace=False)) for k in (505, 520, 1010, 1040)]
    sizes, bits = np.array([len(s) for s in sets]), [dedup.parity(np.sort(s)) for s in sets]
    x, y = dedup.bucket_mates(np.arange(len(sets)), sizes, bits, np.zeros(len(sets), int), False, 0.85, True)
    got = {tuple(sorted(p)) for p in zip(x.tolist(), y.tolist())}
    alike = lambda a, b: len(np.intersect1d(sets[a], sets[b])) / len(np.union1d(sets[a], sets[b]))
    want = {(a, b) for a, b in itertools.combinations(range(len(sets)), 2) if alike(a, b) >= 0.85}
    assert want and want <= got and (8, 0)[::-1] not in got


def test_a_run_keeps_one_table_of_records(spark):
    """each pass left all records on disk, those that it handed on with those that it rejected."""
    import os

    from refinery.operators.storage import shared_dir
    from refinery.plans.run import Curation
    from refinery.records import to_records

    raw = spark.createDataFrame([(k, t) for k, t in enumerate([*word_texts(24), *word_texts(3), "short"])], "k long, text string")
    root = shared_dir(spark).removeprefix("file:")
    before = set(os.listdir(root))
    result = Curation(spark, CurationConfig(dedup="minhash")).run(to_records(raw, {"output": "text"}, "language_modeling", "made", ("k",)))
    left = {x.split("-")[1] for x in set(os.listdir(root)) - before}
    assert not left & {"schema_gate", "dedup_exact"} and {"rejected", "dedup_minhash"} <= left
    assert result.table.count() == 28 and {r.rejecting_step for r in result.rejected.collect()} == {"schema_gate", "dedup_exact", "dedup_minhash"}


def test_vectors_are_written_once_for_all_tables_of_signs(spark, monkeypatch):
    """F16: a vector was written and shuffled once for each table of the index, whether it met another there or not. The pairs are those of shared signs."""
    import numpy as np

    from refinery.operators import dedup

    r = np.random.default_rng(5)
    v = r.standard_normal((60, 64))
    v = np.vstack([v, v[:20] + 0.1 * r.standard_normal((20, 64))]).astype(np.float32)
    written, plain = {}, dedup.materialize
    monkeypatch.setattr(dedup, "materialize", lambda df, name: (out := plain(df, name), written.__setitem__(name, out.count()))[0])
    df = spark.createDataFrame([(f"v{k:02}", x.tolist()) for k, x in enumerate(v)], "id string, embedding array<float>")
    got = {(p.a, p.b): p.cosine for p in dedup.vector_pairs(df, None, 0.9, "lsh", block=8).collect()}
    signs = (v @ np.random.default_rng(7).standard_normal((96, 64)).astype(np.float32).T >= 0).reshape(len(v), 12, 8)
    unit = v.astype(np.float64) / np.linalg.norm(v.astype(np.float64), axis=1, keepdims=True)
    want = {(f"v{a:02}", f"v{b:02}") for a, b in itertools.combinations(range(len(v)), 2) if unit[a] @ unit[b] > 0.9 and (signs[a] == signs[b]).all(axis=1).any()}
    assert set(got) == want and len(want) >= 15 and written["codes"] == len(v)
    assert all(abs(c - unit[int(a[1:])] @ unit[int(b[1:])]) < 1e-9 for (a, b), c in got.items())


def test_encoder_counts_ngrams_as_before(spark):
    import zlib

    import numpy as np

    from refinery.operators.gates import hashed_encoder

    texts = ["", None, "Hello wörld hello", "a", "xyz " * 50]
    rows = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "k int, t string").coalesce(1).withColumn("v", hashed_encoder()("t")).orderBy("k").collect()
    for r in rows:
        v, t = np.zeros(256), f" {(r.t or '').lower()} "
        for k in range(len(t) - 2):
            v[zlib.crc32(t[k : k + 3].encode()) % 256] += 1
        v = np.log1p(v)
        assert np.array_equal(np.array(r.v, np.float32), (v / max(np.linalg.norm(v), 1e-12)).astype(np.float32))


def test_shared_grams_of_pairs(monkeypatch):
    """pairs of a block were met one by one; they are told by one table of bits, whatever its slices."""
    import numpy as np

    from refinery.operators import dedup

    r = np.random.default_rng(3)
    pool = np.unique(r.integers(0, 2**63, 500, dtype=np.uint64))
    grams = [np.sort(r.choice(pool, int(r.integers(1, 400)), replace=False)) for _ in range(40)] + [np.array([2**63 + 5], np.uint64)]
    x, y = np.triu_indices(len(grams), 1)
    want = [len(np.intersect1d(grams[a], grams[b])) for a, b in zip(x, y)]
    monkeypatch.setattr(np, "intersect1d", None)
    assert dedup.shared_grams(grams, x, y).tolist() == want
    for name, value in (("NUMBERED", 300), ("CELLS", 1), ("WORDS", 1)):
        monkeypatch.setattr(dedup, name, value)
        assert dedup.shared_grams(grams, x, y).tolist() == want


def test_normal_form_is_that_of_all_blanks(spark):
    """the normal form leaves single blanks alone, and collapses all others as before."""
    import itertools
    import re

    from refinery.functions import text as tx

    texts = ["".join(p) for k in range(6) for p in itertools.product("a \t\n", repeat=k)] + ["A \x0b\f\r B  c", None]
    rows = spark.createDataFrame([(t,) for t in texts], "t string").select("t", tx.normal_form(tx.F.col("t")).alias("n")).collect()
    assert all(r.n == (None if r.t is None else re.sub("[ \t\n\x0b\f\r]+", " ", r.t.lower()).strip(" ")) for r in rows)


def test_equal_ids_of_a_bucket_over_batches(spark):
    """A bucket goes on over batches of rows; its pairs are those of one batch."""
    from refinery.operators import dedup

    signed = dedup.signatures(spark.createDataFrame(list(enumerate(word_texts(60))), "id long, text string"), 3, 128, 64, 2)
    pairs = lambda: {(r.a, r.b) for r in dedup.candidate_pairs(signed, 16, 0.5).collect()}
    whole = pairs()
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        assert pairs() == whole and len(whole) > 20
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
