"""Parameters, rate schedule and planning formulas of the adaptive sketch."""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class SketchParams:
    """accept None: the theory threshold c_accept ln(n) / eps^2; a number: practical threshold. p0 and cap likewise:
    'theory', 'scaled' (accept / 2n, growth * accept), or a number; cap None: labels are never clipped. rounds 'auto':
    'fused' where all edges fit one task, else 'two'. idle: with log constants, run and number the first levels too
    whose threshold no core of the graph reaches (the level bands are stated of these numbers)."""

    eps: float = 0.25
    c_rate: float = 96
    c_accept: float = 192
    c_cap: float = 384
    accept: float | None = None
    growth: float = 2.0
    p0: str | float = "theory"
    cap: str | float | None = "theory"
    deflate: bool = True
    side: str = "lower"
    exact_last: bool = False
    sampler: str = "nested"
    hash: str = "xxhash64"
    seed: int = 0
    prepeel: int = 0
    peeler: str = "auto"
    max_local_edges: int = 10_000_000
    rounds: str = "auto"
    n_upper: int | None = None
    idle: bool = False

    def __post_init__(self):
        if not 0 < self.eps <= 1 or (self.eps == 1 and self.deflate):
            raise ValueError("eps must lie in (0, 1]; 1 only without deflation")
        if self.eps >= 0.5 and self.deflate:
            warnings.warn("with eps >= 1/2 the bound 1 - 2 eps says nothing", stacklevel=2)
        if self.growth <= 1:
            raise ValueError("growth must exceed 1")
        if self.sampler not in ("nested", "fresh") or self.hash not in ("xxhash64", "md5") or self.peeler not in ("auto", "local", "distributed") or self.rounds not in ("auto", "two", "fused") or self.side not in ("lower", "upper"):
            raise ValueError("unknown option")

    def threshold(self, n: int) -> float:
        return self.c_accept * math.log(max(n, 2)) / self.eps**2 if self.accept is None else self.accept

    def clip(self, n: int) -> float:
        if self.cap is None:
            return math.inf
        if self.cap == "theory" and self.accept is None:
            return self.c_cap * math.log(max(n, 2)) / self.eps**2
        return self.growth * self.threshold(n) if isinstance(self.cap, str) else self.cap

    def first_rate(self, n: int) -> float:
        if n <= 2:
            return 1.0
        if self.p0 == "theory":
            return min(1.0, self.c_rate * math.log(n) / (self.eps**2 * n))
        return min(1.0, self.threshold(n) / (2 * n) if self.p0 == "scaled" else float(self.p0))


@dataclass(frozen=True)
class Level:
    level: int
    rate: float
    accept: float
    cap: float


def rate_schedule(n: int, p: SketchParams) -> list[Level]:
    """Rates from the first one up by `growth`, the last clamped to 1; at rate 1 everything is accepted, unclipped."""
    n = p.n_upper or n
    out, rate = [], p.first_rate(n)
    while True:
        last = rate >= 1
        out.append(Level(len(out), min(rate, 1.0), 0.0 if last else p.threshold(n), math.inf if last else p.clip(n)))
        if last:
            return out
        rate = min(1.0, rate * p.growth)


def without_idle(levels: list[Level], most: int) -> list[Level]:
    """levels from the first one on that can settle a vertex of a graph whose corenesses are `most` at most. A sample
    has no denser cores than its graph, so an earlier one only moves the numbers of the others."""
    first = next(x.level for x in levels if x.rate >= 1 or x.accept <= most)
    return [replace(x, level=x.level - first) for x in levels[first:]]


def deflation(level: Level, p: SketchParams) -> float:
    """What an estimate of this level is multiplied by."""
    factor = 1.0 if not p.deflate or (p.exact_last and level.rate >= 1) else 1 - p.eps
    return factor / (1 - 2 * p.eps) if p.side == "upper" else factor


def label_of(raw: float, level: Level, p: SketchParams) -> float:
    """The label of an accepted vertex."""
    return deflation(level, p) * min(raw, level.cap) / level.rate


def plan_space(n: int, p: SketchParams) -> dict[str, float]:
    """Predicted edges: the bound on one level and on all, and the practical rule accept * n."""
    levels, log_n = len(rate_schedule(n, p)), math.log(max(n, 2))
    one = 4 * p.c_rate * (1 + p.eps) ** 2 / p.eps**2 * n * log_n
    return {"levels": levels, "bound_max": one, "bound_sum": one * levels, "rule_max": p.threshold(n) * n}


def recommend_growth(mode: str, budget: float, n: int, accept: float) -> float:
    """Growth factor: small when one level must fit ('max'), large when all levels together must ('sum')."""
    if mode == "max":
        tight = budget / (accept * n)
        return 2.0 if tight >= 1 else 1.6 if tight >= 0.75 else 1.4 if tight >= 0.5 else 1.2
    if mode == "sum":
        loose = budget / (accept * n)
        return 2.0 if loose < 3 else 1.6 if loose < 4 else 1.4 if loose < 6 else 1.2
    raise ValueError("mode is 'max' or 'sum'")
