"""Hyper-parameters as frozen values, with the published presets per class of data."""

from __future__ import annotations

from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class HashConfig:
    """Hashed neighbour search: G bits a code, p codes a group, q groups, K neighbours."""

    G: int = 8
    p: int = 3
    q: int = 100
    K: int = 32
    psi: str = "square"
    seed: int = 7
    family: str = "portable"  # portable: md5 (same bits in any engine); fast: xxhash64
    max_bucket: int | None = 1000  # buckets above it are joined block by block; no pair is lost

    @property
    def reps(self) -> int:
        return self.p * self.q


@dataclass(frozen=True)
class Rates:
    """Initial step and penalty of each parameter group."""

    b: float = 0.02
    bh: float = 0.02
    u: float = 0.02
    v: float = 0.02
    w: float = 0.001
    c: float = 0.001


@dataclass(frozen=True)
class TrainConfig:
    F: int = 32
    K: int = 32
    alpha: Rates = field(default_factory=Rates)
    lam: Rates = field(default_factory=lambda: Rates(0.01, 0.01, 0.01, 0.01, 0.05, 0.05))
    beta: float = 0.3
    epochs: int = 20
    target: float | None = None
    parts: frozenset = frozenset({"base", "explicit", "implicit", "factor"})
    implicit: str = "complement"
    loss: str = "squared"  # or logistic
    residual: str = "frozen"  # or live
    order: str = "degree"  # degree, id, hashed
    side: str = "row"
    D: int = 4
    seed: int = 11
    use_bias: bool = True
    batch_gain: float = 10.0  # minibatch form of the entry-parallel baseline: one averaged step an epoch is taken this much longer

    def but(self, **changes) -> "TrainConfig":
        return replace(self, **changes)


def factor_config(alpha: float, beta: float, lam: float, **more) -> TrainConfig:
    return TrainConfig(alpha=Rates(0, 0, alpha, alpha, 0, 0), lam=Rates(0, 0, lam, lam, 0, 0), beta=beta, parts=frozenset({"factor"}), use_bias=False, **more)


def blend_config(a: float, a_n: float, lam: float, lam_n: float, **more) -> TrainConfig:
    return TrainConfig(alpha=Rates(a, a, a, a, a_n, a_n), lam=Rates(lam, lam, lam, lam, lam_n, lam_n), **more)


# Published rates, penalties, weightings and targets for the three classes of rating data
# (1 to 5 stars; 0.5 to 5 stars; 0.5 to 100, trained on values divided by 20).
FACTOR_PRESETS = {"stars": factor_config(0.04, 0.3, 0.035), "halves": factor_config(0.04, 0.3, 0.035), "hundred": factor_config(0.01, 0.1, 0.02)}
BLEND_PRESETS = {"stars": blend_config(0.02, 0.001, 0.01, 0.05), "halves": blend_config(0.035, 0.002, 0.02, 0.002), "hundred": blend_config(0.02, 0.001, 0.02, 0.05)}
PSI_PRESETS = {"stars": "square", "halves": "square", "hundred": "fourth"}
TARGET_RMSE = {"stars": 0.92, "halves": 0.80, "hundred": 22.0}
NOISE_RATES = (0.01, 0.005, 0.001, 0.0005, 0.0001)
LAMBDA_RHO = 100.0
