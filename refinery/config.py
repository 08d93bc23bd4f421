"""Flat run configuration: frozen, patched by copy, hashed without secrets."""

from __future__ import annotations

import dataclasses
import hashlib
import json
from dataclasses import dataclass, field
from typing import Any

GATES = ("grounding", "reward", "diversity")
DEFAULT_PII = ("person", "email", "phone", "us_ssn", "credit_card", "ip_address", "us_bank", "iban")
CLINICAL_PII = (*DEFAULT_PII, "date_time", "location", "medical_licence")
REWARD_DIMENSIONS = ("helpfulness", "honesty", "instruction_following", "truthfulness", "depth", "creativity", "coherence")
CLEAN_TRANSFORMS = ("html", "mojibake", "unicode", "control", "whitespace")
EXPORTS = ("alpaca", "sharegpt", "pairs", "rollouts", "ppo", "corpus")


@dataclass(frozen=True)
class CurationConfig:
    """Every setting of a run, in one flat namespace; unknown names and values out of range raise before any job."""

    # sources
    sources: tuple = ()
    split: str | None = None
    subset: str | None = None
    max_samples_per_source: int | None = None
    data_key: str | None = None
    csv_header: str = "auto"
    csv_sep: str | None = None
    json_cells: bool = True
    hub_streaming: bool = False
    field_mapping: dict = field(default_factory=dict)
    preprocess_fn: Any = None
    detect_rows: int = 10
    detect_min_tier: str = "LOW"
    task_type: str | None = None
    # chunking
    chunk_strategy: str = "heading"
    chunk_max_tokens: int = 512
    chunk_overlap_tokens: int = 50
    extract_tables: bool = False
    pdf_output_mode: str = "chunk"
    # schema gate
    schema_gate: bool = True
    min_tokens: int = 10
    max_tokens: int = 4096
    tokenizer: str = "whitespace"
    vocabulary_path: str | None = None
    check_encoding: bool = True
    # cleaning
    clean: bool = False
    clean_transforms: tuple = CLEAN_TRANSFORMS
    keep_newlines: bool = True
    # deduplication
    dedup: str = "none"
    dedup_policy: str = "greedy"
    minhash_threshold: float = 0.85
    minhash_n: int = 3
    minhash_num_perm: int = 128
    minhash_bands: int | None = None
    minhash_verify: bool = True
    embedding_dedup: bool = False
    embedding_threshold: float = 0.92
    index_dir: str | None = None
    index_kind: str = "auto"
    reset_index: bool = False
    # sampling
    resample: bool = False
    resample_field: str = "source_uri"
    target_distribution: dict = field(default_factory=dict)
    resample_basis: str = "input"
    untargeted: str = "keep"
    max_samples: int | None = None
    sample_seed: int = 0
    # secrets
    secrets_gate: bool = False
    secrets_code_mode: bool = False
    secrets_hex_limit: float = 3.0
    secrets_base64_limit: float = 4.5
    secrets_quoted_only: bool = True
    secrets_mode: str = "reject"
    secrets_fields: tuple | None = None
    log_secrets: bool = False
    # personal data
    pii: bool = False
    pii_entities: tuple = DEFAULT_PII
    pii_threshold: float = 0.7
    pii_seed: int = 0
    pii_mode: str = "pseudonym"
    pii_fields: tuple | None = None
    # toxicity
    toxicity_gate: bool = False
    toxicity_pass: float = 0.1
    toxicity_reject: float = 0.5
    toxicity_scorer: str = "unbiased"
    toxicity_judge: bool = False
    toxicity_judge_reject: float = 0.5
    toxicity_fields: tuple | None = None
    # models
    generator_model: str = "offline-extractive"
    generator_temperature: float = 0.7
    generator_concurrency: int = 16
    judge_model: str = "offline-overlap"
    judge_temperature: float = 0.1
    judge_concurrency: int = 8
    probe_model: str | None = None
    api_base: str | None = None
    api_key: str | None = None
    extra_body: dict = field(default_factory=dict)
    max_retries: int = 3
    backoff_base: float = 0.5
    strip_think: bool = True
    call_budget: int | None = None
    ledger_dir: str | None = None
    async_mode: bool = True
    # generation
    task: str | None = None
    num_questions: int = 3
    difficulty: str = "medium"
    multi_passage: bool = False
    preference_mode: str = "two_pass"
    rejected_temperature: float = 1.2
    num_responses: int = 4
    rollout_temperatures: tuple = ()
    rollout_spread: float = 0.6
    score_responses: bool = False
    dialogue_mode: str = "turn_by_turn"
    num_turns: int = 3
    evolve_strategies: tuple = ("constraints", "deepen", "concretise", "reasoning", "broaden")
    evolve_answer: bool = False
    cot_mode: str = "generate"
    inject_rate: float = 0.2
    inject_types: tuple = ("contradicts_source", "parametric_drift", "domain_mismatch", "instruction_quality")
    parse_retries: int = 1
    prompt_templates: dict = field(default_factory=dict)
    # gates
    gates: tuple = ()
    grounding_threshold: float = 0.7
    reward_threshold: float = 0.7
    reward_dimensions: tuple = REWARD_DIMENSIONS
    reward_prompt: str | None = None
    diversity_threshold: float = 0.92
    encoder: str = "hashed-3gram"
    evidence: str = "exact"
    # recovery
    recovery: str = "none"
    probe_temperatures: tuple = (0.3, 0.5)
    probe_score_split: float = 0.5
    probe_on: tuple = ("grounding",)
    probe_max_calls: int = 5
    refiner: bool = False
    refine_template: str | None = None
    retry_max: int = 5
    # export
    export_formats: tuple = ()
    output_split: dict = field(default_factory=dict)
    split_seed: int = 0
    output_dir: str | None = None
    single_file: bool = False
    run_ts: str = "1970-01-01T00:00:00Z"
    run_id: str = "run"
    verbose: bool = False

    def __post_init__(self):
        self.validate()

    def validate(self) -> None:
        one_of = {
            "dedup": ("none", "exact", "minhash"), "dedup_policy": ("greedy", "component"), "tokenizer": ("whitespace", "bpe"), "chunk_strategy": ("heading", "fixed", "paragraph"),
            "pdf_output_mode": ("chunk", "qa", "preference", "rollout", "multiturn"), "index_kind": ("auto", "exact", "lsh"), "resample_basis": ("input", "feasible"), "untargeted": ("keep", "reject"),
            "secrets_mode": ("reject", "redact"), "pii_mode": ("pseudonym", "mask"), "preference_mode": ("single_call", "two_pass"), "dialogue_mode": ("turn_by_turn", "single_call"),
            "difficulty": ("easy", "medium", "hard"), "cot_mode": ("generate", "wrap"), "evidence": ("exact", "retrieved"), "recovery": ("none", "adaptive", "retry"), "toxicity_scorer": ("unbiased", "original", "multilingual"),
        }
        for name, values in one_of.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} must be one of {values}, not {getattr(self, name)!r}")
        for name in ("minhash_threshold", "embedding_threshold", "toxicity_pass", "toxicity_reject", "pii_threshold", "grounding_threshold", "reward_threshold", "diversity_threshold", "probe_score_split", "inject_rate"):
            if not 0 <= getattr(self, name) <= 1:
                raise ValueError(f"{name} must lie in [0, 1]")
        if self.min_tokens > self.max_tokens:
            raise ValueError("min_tokens exceeds max_tokens")
        if self.toxicity_pass > self.toxicity_reject:
            raise ValueError("toxicity_pass exceeds toxicity_reject")
        if self.tokenizer == "bpe" and not self.vocabulary_path:
            raise ValueError("the bpe tokenizer needs vocabulary_path")
        from refinery.operators.gates import CUSTOM_GATES, ENCODERS
        from refinery.operators.generation import EVOLUTIONS, INJECTIONS
        from refinery.operators.tasks import TASKS, templates_of

        if self.task not in (None, *TASKS):
            raise ValueError(f"task must be one of {TASKS}, not {self.task!r}")
        if self.encoder not in ENCODERS:
            raise ValueError(f"encoder must be one of {sorted(ENCODERS)}, not {self.encoder!r}")
        if not 0 <= self.chunk_overlap_tokens < self.chunk_max_tokens:
            raise ValueError("chunk_overlap_tokens must be below chunk_max_tokens")
        if self.recovery == "adaptive" and len(self.probe_temperatures) + 3 > self.probe_max_calls:
            raise ValueError("probe_max_calls must allow for every temperature and three prompts")
        templates_of(self)
        for name, known in (("gates", (*GATES, *CUSTOM_GATES)), ("evolve_strategies", EVOLUTIONS), ("inject_types", INJECTIONS), ("probe_on", ("grounding", "reward")), ("clean_transforms", CLEAN_TRANSFORMS), ("export_formats", EXPORTS), ("pii_entities", CLINICAL_PII), ("reward_dimensions", REWARD_DIMENSIONS)):
            if odd := set(getattr(self, name)) - set(known):
                raise ValueError(f"unknown {name}: {sorted(odd)}")
        for name in ("target_distribution", "output_split"):
            shares = getattr(self, name)
            if shares and abs(sum(shares.values()) - 1) > 1e-9:
                raise ValueError(f"{name} must sum to 1")

    def warnings(self) -> list[str]:
        """Settings that are allowed but switch something off."""
        out = []
        if self.secrets_hex_limit > 4.0:
            out.append("secrets_hex_limit above 4.0 bits, the most a hex string can have: hex detection is off")
        if self.secrets_base64_limit > 6.0:
            out.append("secrets_base64_limit above 6.0 bits, the most a base64 string can have: base64 detection is off")
        return out

    def patch(self, changes: dict) -> CurationConfig:
        """A copy with some fields changed; the original stays as it was. Unknown names raise."""
        if odd := set(changes) - {f.name for f in dataclasses.fields(self)}:
            raise ValueError(f"unknown settings: {sorted(odd)}")
        return dataclasses.replace(self, **changes)

    def digest(self) -> str:
        """SHA-256 of the settings as sorted JSON, the key left out and functions by name."""
        plain = {f.name: getattr(self, f.name) for f in dataclasses.fields(self) if f.name != "api_key"}
        return hashlib.sha256(json.dumps(plain, sort_keys=True, default=lambda x: getattr(x, "__qualname__", str(x))).encode()).hexdigest()


PRESETS = {
    "clinical": {"pii_entities": CLINICAL_PII},
    "sensitive": {"toxicity_pass": 0.2},
    "code": {"secrets_code_mode": True},
}


def load(path: str) -> CurationConfig:
    """Settings from a YAML file of flat names, or of sections (each a mapping) whose names are dropped."""
    import yaml

    with open(path) as f:
        given = yaml.safe_load(f) or {}
    names = {f.name for f in dataclasses.fields(CurationConfig)}
    flat: dict = {}
    for preset in given.pop("presets", []):
        flat |= PRESETS[preset]
    for k, v in given.items():
        flat |= {k: v} if k in names or not isinstance(v, dict) else v
    if odd := set(flat) - names:
        raise ValueError(f"unknown settings: {sorted(odd)}")
    flat = {k: tuple(v) if isinstance(v, list) else v for k, v in flat.items()}
    return CurationConfig(**flat)
