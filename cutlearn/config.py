"""Settings, workloads and errors; the one place where their values stand."""

from __future__ import annotations

from dataclasses import dataclass, field


class CutError(ValueError):
    """Base of what this package raises."""


class GridTooCoarse(CutError):
    """More regions are wanted than the grid can be cut into."""


class InvalidLayout(CutError):
    """Rectangles overlap or leave cells uncovered."""


class EmptyInput(CutError):
    """There are no points to fit a map to."""


class BadWorkload(CutError):
    """Frequencies don't sum to one."""


#: Frequencies of the three thresholds in the two skews, and the thresholds in map units.
SKEWS = {"small": (0.25, 0.5, 0.25), "large": (0.02, 0.03, 0.95)}
THRESHOLDS = {"geo_hot": (500, 1000, 5000), "events_xy": (500, 1000, 5000), "lineitem_xy": (500, 1000, 5000), "embed_xy": (50, 100, 500)}


@dataclass(frozen=True)
class DistanceJoin:
    d: int
    freq: float


@dataclass(frozen=True)
class Workload:
    queries: tuple[DistanceJoin, ...]

    def __post_init__(self) -> None:
        if not self.queries or abs(sum(q.freq for q in self.queries) - 1) > 1e-9:
            raise BadWorkload("frequencies must sum to 1")

    @staticmethod
    def of(dataset: str, skew: str) -> Workload:
        return Workload(tuple(DistanceJoin(d, f) for d, f in zip(THRESHOLDS[dataset], SKEWS[skew], strict=True)))

    @property
    def freqs(self) -> tuple[float, ...]:
        return tuple(q.freq for q in self.queries)


@dataclass(frozen=True)
class Environment:
    m: int = 8
    local_index: bool = True
    conf: dict[str, str] = field(default_factory=dict)


@dataclass(frozen=True)
class TrainConfig:
    """The first block holds published settings, the second our own choices."""

    g: int = 30
    eps_random: float = 0.1
    eps_shift: float = 0.2
    agent_cap: int = 10_000
    demo_cap: int = 100
    batch: int = 32
    rho: float = 0.25
    n_step: int = 3
    discount: float = 0.99
    hidden: tuple[int, ...] = (1200, 600)
    rate: float = 0.001
    lambdas: tuple[float, float, float] = (1.0, 1.0, 1e-5)
    stop_factor: float = 2.0
    stop_reward: float = 0.2
    repeats: int = 3
    episodes: int = 5000
    wall_cap_s: float = 120 * 3600.0

    pretrain_iters: int = 5000
    target_every: int = 100
    margin: float = 0.8
    alpha: float = 0.6
    beta: float = 0.4
    priority_floor: float = 1e-3
    clip: float = 10.0
    seed: int = 42
    bootstrap: str = "max_target"  # or "double"
    discount_bootstrap: bool = True
    reward_kind: str = "mean_of_ratios"  # or "ratio_of_means"
    shift: str = "perpendicular"  # or "neighbour"
    shift_given_greedy: bool = False
    shift_base: str = "model"  # or "best_layout": beside a cut of the best layout so far
    renormalise_rewards: bool = False  # stored rewards follow the best layout when it changes
    refresh_best_every: int = 0  # episodes between new measurements of the best layout; 0 for never
    mass_scale: str = "literal"  # or "unit"
    pretrain: bool = True
    grid_shift: bool = True
    exec_stop: bool = True


#: Arms of the ablation as changes to a TrainConfig.
ARMS = {
    "none": {"pretrain": False, "grid_shift": False, "exec_stop": False},
    "no_pretrain": {"pretrain": False},
    "no_shift": {"grid_shift": False},
    "no_stop": {"exec_stop": False},
    "all": {},
}
