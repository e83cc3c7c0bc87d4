"""All thresholds, weights and switches of the curation stages, as immutable records."""

from __future__ import annotations

from dataclasses import dataclass, field

# Published thresholds of the first stage, detector increments in tenths, and the eight dimension names.
DOC_CHARS = (20, 10_000)
COMPLEXITY = (1, 50)
MIN_LOGICAL_LINES = 5
ACCESSOR_PREFIXES = ("get", "set", "is", "has")
TEST_PATTERNS = ("test_", "test", "Test", "TEST", "_test")
PLACEHOLDERS = ("TODO", "FIXME")
DETECTOR_TENTHS = {"phrase": 3, "structure": 2, "completeness": 2, "generic": 1}
DIMENSIONS = ("completeness", "param_coverage", "return_doc", "types", "clarity", "structure", "complexity", "code_quality")


@dataclass(frozen=True)
class Stage1Config:
    min_doc_chars: int = DOC_CHARS[0]
    max_doc_chars: int = DOC_CHARS[1]
    min_complexity: int = COMPLEXITY[0]
    max_complexity: int = COMPLEXITY[1]
    min_logical_lines: int = MIN_LOGICAL_LINES
    max_logical_lines: int | None = None
    accessor_match: str = "boundary_and_small"  # prefix | boundary | boundary_and_small
    accessor_max_lines: int = 12
    test_match: str = "affix"  # substring | affix | boundary
    placeholders: tuple[str, ...] = PLACEHOLDERS
    placeholder_case_sensitive: bool = True
    exclude_examples: bool = True

    @classmethod
    def table(cls) -> Stage1Config:
        """Only the printed threshold rows: examples stay in."""
        return cls(exclude_examples=False)


@dataclass(frozen=True)
class Stage2Config:
    weights: tuple[int, ...] = (20, 15, 15, 10, 15, 10, 5, 10)
    min_score: float = 6.0
    missing: str = "renormalise"  # renormalise | zero

    def __post_init__(self):
        if len(self.weights) != len(DIMENSIONS) or any(w <= 0 for w in self.weights):
            raise ValueError("eight positive weights are needed")

    @classmethod
    def equal(cls) -> Stage2Config:
        return cls(weights=(1,) * len(DIMENSIONS))


@dataclass(frozen=True)
class DedupConfig:
    num_hashes: int = 128
    bands: int = 32
    rows: int = 4
    tau_lsh: float = 0.8
    seed: int = 7
    family: str = "affine31"  # affine31 | xxhash64
    verify: str = "exact"  # none | signature | exact


@dataclass(frozen=True)
class DetectorConfig:
    tau_ai_tenths: int = 5
    count: str = "per_signal"  # per_signal | per_match
    policy: str = "mark"  # mark | drop
    min_sections: int = 4
    phrases: tuple[str, ...] = (
        "as an ai", "it is important to note", "this function is designed to", "in this example, we", "please note that", "feel free to",
    )
    generic: tuple[str, ...] = ("performs the operation", "handles the logic", "helper function", "utility function", "does the work")


@dataclass(frozen=True)
class TrainingConfig:
    """Recorded settings of the adapter fine-tuning run; the training itself is outside this engine."""

    split: tuple[float, float, float] = (0.8, 0.1, 0.1)
    seed: int = 3407
    max_tokens: int = 2048
    per_device_batch: int = 2
    accumulation: int = 4
    epochs: int = 3
    warmup_steps: int = 50
    peak_rate: float = 1e-4
    adapter_rank: int = 16
    adapter_scale: int = 16
    quantised_bits: int = 4
    packing: bool = True


@dataclass(frozen=True)
class CurationConfig:
    stage1: Stage1Config = field(default_factory=Stage1Config)
    stage2: Stage2Config = field(default_factory=Stage2Config)
    dedup: DedupConfig = field(default_factory=DedupConfig)
    detector: DetectorConfig = field(default_factory=DetectorConfig)
    training: TrainingConfig = field(default_factory=TrainingConfig)
