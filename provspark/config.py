"""Parameters of the methods, all overridable; defaults are this engine's own unless said otherwise."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class AuditPolicy:
    """Bands of similarity: at least ``accept`` is taken, below ``review`` is rejected, between waits for a decision."""

    accept: float = 0.9
    review: float = 0.8
    keep_per_item: int = 1

    @staticmethod
    def accept_all(threshold: float) -> AuditPolicy:
        return AuditPolicy(accept=threshold, review=threshold)


@dataclass(frozen=True)
class ScaleLaw:
    """f(M) = a + b log10(M / 1e9)."""

    a: float
    b: float = 0.0


@dataclass(frozen=True)
class ScoringConfig:
    """Coefficients of the quality score.

    The three weights of Q come from a least-squares fit of the published score parts at two sizes;
    nothing else could be recovered and the rest are documented defaults.
    """

    con: float = 0.4
    mcq: float = 0.3
    mcq_penalty: float = 0.5
    reuse: float = 0.3
    reuse_free: int = 2
    reuse_form: str = "inverse"
    diversity: float = 0.1
    clip_learnability: bool = False
    verifiability_weight: ScaleLaw = ScaleLaw(0.35)
    learnability_weight: ScaleLaw = ScaleLaw(0.30)
    contamination_weight: ScaleLaw = ScaleLaw(0.35)
    gain_share: ScaleLaw = ScaleLaw(0.4, 0.3)
    alpha01: ScaleLaw = ScaleLaw(1.0)
    alpha11: ScaleLaw = ScaleLaw(0.3)
    alpha10: ScaleLaw = ScaleLaw(0.2)
    alpha00: ScaleLaw = ScaleLaw(-0.5)
    w1: ScaleLaw = ScaleLaw(0.684, -0.363)
    w2: ScaleLaw = ScaleLaw(0.220, 0.131)
    w3: ScaleLaw = ScaleLaw(0.096, 0.232)
    scales: tuple[float, ...] = (1.7e9, 8.0e9)
    names: tuple[str, ...] = field(default=("small", "large"))


#: Share of unmatched items below which recovery stops.
STOP_SHARE = 0.01
#: Items looked at in each set when its format is inspected.
INSPECTED = 40
#: Similarities at which a match to a benchmark counts as sure, and as possible.
SURE, POSSIBLE = 0.9, 0.8
#: Retrieved candidates for each unmatched item.
TOP_K = 5
SEED = "provspark"
