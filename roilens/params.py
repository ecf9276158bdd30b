"""All options in one frozen record, with the defaults of SURVEY 2.11; values are checked when made."""

from __future__ import annotations

from dataclasses import dataclass, replace

CHOICES = {
    "strategy": ("fixed", "idle", "drift"),
    "evidence": ("gap", "still", "either"),
    "detector": ("tiered", "interp", "cusum"),
    "stretch": ("printed", "intent", "none"),
    "stretch_on": ("polygon", "roi"),
    "pairs": ("all", "cross_segment"),
    "hull": ("chain", "angular"),
    "per": ("point", "value"),
    "update": ("sequential", "batch"),
    "softmax": ("view", "state", "none"),
    "peculiarity": ("printed", "intent", "plain"),
    "peculiar_on": ("after", "before"),
    "guard": ("intent", "printed"),
    "swap": ("first", "best"),
    "diversity": ("mean", "sum", "min"),
    "fuzzy": ("topk_mean", "cmeans"),
    "thinning": ("grid", "refractory"),
}
#: Sampling gaps by a user's profile: novices move more at random, so their signal is sampled less often.
PROFILE_EPS = {"novice": 250, "regular": 100, "expert": 50, "delivery": 50, "tourism": 100, "transportation": 100}


@dataclass(frozen=True)
class Params:
    eps_ms: int = 100
    thinning: str = "grid"
    strategy: str = "fixed"
    g: int | str | None = 3  # "auto": from the density of points on the map
    length_ms: int | None = None
    horizon_ms: int = 30_000
    keep_open: bool = True
    tau_ms: int = 300
    evidence: str = "either"
    detector: str = "tiered"
    widths: tuple[int, ...] = (4, 8, 16)
    drift_threshold: float = 1.0
    radius: float = 30.0
    min_pts: int = 5
    strict: bool = True
    count_self: bool = True
    eps_t: int | None = None
    delta_mean: float | None = None
    local_cap: int = 4096
    prune_directions: int = 8
    hull: str = "chain"
    xi: float = 7.0
    rounds_done: int = 1
    stretch: str = "printed"
    stretch_on: str = "polygon"
    pairs: str = "all"
    min_support: int = 2
    boundary: bool = False
    capacity: int = 64
    max_depth: int = 11
    use_index: bool = True
    delta: float = 0.05
    per: str = "point"
    update: str = "sequential"
    softmax: str = "view"
    k: int = 5
    peculiarity: str = "printed"
    peculiar_on: str = "after"
    guard: str = "intent"
    threshold: float = 0.3
    swap: str = "first"
    diversity: str = "mean"
    time_limit_ms: int | None = None
    max_scan: int | None = None
    weights: tuple[float, float, float] = (0.5, 0.25, 0.25)
    fuzzy: str = "topk_mean"
    fuzzifier: float = 2.0
    tol: float = 1e-3
    max_iter: int = 20
    viewport: tuple[int, int] = (1600, 900)

    def __post_init__(self):
        for name, allowed in CHOICES.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}, not {getattr(self, name)!r}")
        if self.eps_ms <= 0 or self.radius <= 0 or self.min_pts < 1 or self.k < 0 or self.min_support < 1:
            raise ValueError("eps_ms and radius must be positive, min_pts and min_support at least 1, k not negative")
        if not (self.g is None or self.g == "auto" or isinstance(self.g, int)):
            raise ValueError("g must be a number, 'auto' or None")
        if self.prune_directions not in (0, 4, 8):
            raise ValueError("prune_directions must be 0, 4 or 8")

    def but(self, **changes) -> Params:
        return replace(self, **changes)

    @staticmethod
    def eps_for(profile: str) -> int:
        """The sampling gap that suits an application or a user's expertise."""
        return PROFILE_EPS[profile]

    @property
    def diagonal(self) -> float:
        return float(self.viewport[0] ** 2 + self.viewport[1] ** 2) ** 0.5
