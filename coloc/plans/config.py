"""Settings of a mining run."""

from __future__ import annotations

from dataclasses import dataclass, field

from coloc.functions import decay as decays


@dataclass(frozen=True)
class MinerConfig:
    objective: str = "rules"  # rules, patterns
    mode: str = "uncertain"  # uncertain, certain
    step: float = 1.0
    box: tuple[float, float, float, float] | None = None  # None: from the objects
    metric: str = "planar"  # planar, geodesic
    decay: decays.Decay = field(default_factory=decays.cosine)
    dmax: str = "ray"
    combine: str = "max"
    gamma: float = 0.3  # stretching of wind ellipses
    d: int = 3
    effect: str | None = None
    min_exp_sup: float | None = None
    sims: int = 99
    alpha: float = 0.05
    randomise: str = "both"  # both, causes, effects, uniform
    draws: str = "digest"  # digest, bijection: the order in which causes change places
    apportion: str = "largest_remainder"  # largest_remainder, draw: how urban effects fill zones
    seed: str = ""
    early_stop: bool = True
    sim_batch: int = 33
    strategy: str = "cells"
    strict: bool = False

    @property
    def measure(self) -> str:
        if self.objective == "rules":
            return "exp_conf" if self.mode == "uncertain" else "conf"
        return "exp_sup" if self.mode == "uncertain" else "sup"
