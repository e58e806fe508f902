"""Options of a compression, with their defaults and checks."""

from __future__ import annotations

from dataclasses import dataclass, replace

BACKENDS = ("none", "chunk", "chunk_budgeted", "random", "raw_lsh", "local", "adaptive", "global", "dense")


@dataclass(frozen=True)
class CompressOptions:
    rho: float = 4.0
    backend: str = "adaptive"
    window: int = 16
    rff_dim: int = 256
    rank: int = 16
    #: Coordinates that hashing sees; None: as many as the rank.
    top_k: int | None = None
    #: 'random': any start vector; 'range': one in the range of the features, so equal tokens stay equal.
    start: str = "range"
    #: Scale of the coordinates by their eigenvalues: 'none', 'sqrt' or 'full'.
    weighting: str = "sqrt"
    drop_top: bool = True
    #: 'gaussian': the kernel that the cosine features estimate; 'softmax': with the factor of the norms.
    kernel: str = "gaussian"
    #: 'none', or 'row' for the operator divided by its row sums.
    kernel_norm: str = "none"
    bits: int | None = None
    prefix: int = 0
    suffix: int = 12
    position_scheme: str = "max"
    position_mode: str = "representative"
    renorm: str = "member_mean"
    threshold: float = 0.70
    schedule: str = "linear"
    tiny: int = 4
    bypass_rho: float = 16.0
    seed: int = 0
    breakdown_tol: float = 1e-8
    identity_test: bool = False
    #: Share of one common direction in the token vectors, and how words share parts: 'none' or 'trigram'.
    anisotropy: float = 0.25
    subword: str = "trigram"

    def __post_init__(self):
        allowed = {
            "backend": BACKENDS, "start": ("random", "range"), "weighting": ("none", "sqrt", "full"), "kernel": ("gaussian", "softmax"), "kernel_norm": ("none", "row"),
            "position_scheme": ("max", "median", "mean"), "position_mode": ("representative", "compact"), "renorm": ("none", "member_mean", "table_mean", "prompt_mean"),
            "schedule": ("linear", "log2", "constant"), "subword": ("none", "trigram"),
        }
        for name, values in allowed.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} must be one of {values}, not {getattr(self, name)!r}")
        if self.window < 1 or self.rff_dim < 1 or self.rank < 1 or self.rho <= 0:
            raise ValueError("window, rff_dim, rank and rho must be positive")

    def as_printed(self) -> CompressOptions:
        """The spectral settings of the published description rather than ours."""
        return replace(self, start="random", weighting="none", drop_top=False)
