"""Similarities, sketch settings and the calculators that choose them; driver-side scalars only."""

from __future__ import annotations

import math
import random
from dataclasses import dataclass


@dataclass(frozen=True)
class Similarity:
    """A rational set similarity: weights of the intersection, of what neither set has, and of the symmetric difference
    in numerator and denominator."""

    name: str
    x: int
    y: int
    z: int
    zp: int

    @property
    def is_metric(self) -> bool:
        """Whether 1 - S is a metric, which is the same as having a locality sensitive family."""
        return self.zp >= max(self.x, self.y, self.z)

    def is_lshable(self, a: float = 1.0) -> bool:
        """Whether the root similarity with exponent a has a locality sensitive family."""
        return self.zp >= (a + 1) / 2 * max(self.x, self.y) and self.zp >= self.z


# The presets by name.
JACCARD = Similarity("jaccard", 1, 0, 0, 1)
HAMMING = Similarity("hamming", 1, 1, 0, 1)
ANDERBERG = Similarity("anderberg", 1, 0, 0, 2)
ROGERS_TANIMOTO = Similarity("rogers_tanimoto", 1, 1, 0, 2)
DICE = Similarity("dice", 2, 0, 0, 1)
PRESETS = (JACCARD, HAMMING, ANDERBERG, ROGERS_TANIMOTO, DICE)


@dataclass(frozen=True)
class SketchParams:
    """Settings of the leveled bucket sketch and its filter. log_m: bits of the level hash; buckets: a power of two."""

    log_m: int = 16
    buckets: int = 512
    alpha: float = 0.05
    r1: float = 0.5
    rows: int = 5
    bands: int = 40
    seed: int = 7
    window: str = "wide"
    bucket_hash: str = "shared"

    def draw(self, purpose: str, count: int) -> list[tuple[int, int]]:
        """Independent (odd a, b) pairs of a multiply-add-shift family for one purpose."""
        r = random.Random(f"{self.seed}:{purpose}")
        return [(r.getrandbits(32) | 1, r.getrandbits(32)) for _ in range(count)]

    @property
    def step(self) -> int:
        return max(1, math.floor(math.log2(1 / self.r1) + 1e-12))

    @property
    def width(self) -> float:
        """Width of the window of levels: the wide one makes sure that sets of size ratio r1 or more share a level."""
        t = math.log2(1 / self.r1)
        return t + self.step if self.window == "wide" else t

    @property
    def grid(self) -> list[int]:
        return list(range(0, self.log_m + 1, self.step))


def max_level(sim: Similarity, eps: float, delta: float, r: float, size: float) -> float:
    """Highest sampling level at which the sample's similarity is within 1 +- eps. size: |A|, or |U| where y > 0."""
    return math.log2(eps**2 * delta * r * size / (100 * sim.zp))


def theory_alpha(eps: float, delta: float) -> float:
    return eps**2 * delta / 600


def sample_bound(eps: float, delta: float, r1: float) -> float:
    """Sampled items of a union at the estimation level, with probability 1 - delta / 3."""
    return 1800 / (eps**2 * delta**2 * r1)


def theory_buckets(eps: float, delta: float, r1: float) -> float:
    return 1 / (eps**4 * delta**5 * r1**2)


def theory_bits(eps: float, delta: float, r1: float, universe: int) -> float:
    """Order of the sketch's size per set."""
    return theory_buckets(eps, delta, r1) * math.log2(universe) ** 2


def sensitivity(eps: float, delta: float, r1: float, r2: float) -> tuple[float, float, float, float]:
    """(r1, r2, p1, p2) of the filter."""
    return r1, r2, (1 - eps) * r1, 6 * r2 / (delta * (1 - eps / 5 * (2 * r1) ** 0.5))


def useful(eps: float, delta: float, r1: float, r2: float) -> bool:
    _, _, p1, p2 = sensitivity(eps, delta, r1, r2)
    return p1 > p2


def gray_zone(r1: float) -> float:
    """Below this similarity pairs should not be reported (rule of thumb)."""
    return r1**1.5


def detect_probability(s: float, rows: int, bands: int) -> float:
    """Chance that one of the bands agrees in all its rows."""
    return 1 - (1 - s**rows) ** bands


def ratio_bounds(eps: float) -> tuple[float, float]:
    """Worst ratios of two values that are each within 1 +- eps, beside their simpler bounds' holding."""
    return (1 - eps) / (1 + eps), (1 + eps) / (1 - eps)


def sample_variance_bounds(sim: Similarity, num_k: float, den_k: float) -> tuple[float, float]:
    """Bounds on the variances of numerator and denominator in a sample, from their expectations."""
    return max(sim.x + sim.y, sim.z + sim.y, sim.y) * num_k, 2 * sim.zp * den_k


def failure_bound(sim: Similarity, eps: float, k: int, num: float) -> float:
    return 50 * sim.zp * 2**k / (eps**2 * num)


def plan_buckets(alpha: float, r1: float, room: float = 4.0) -> dict[str, float]:
    """Samples at visited levels, and the buckets that hold the most of them with little collision."""
    most = 1 / (alpha * r1**2)
    return {"least": 1 / alpha, "at_estimate": 1 / (alpha * r1), "most": most, "buckets": 2 ** math.ceil(math.log2(room * most))}


def flip_rates(similarity: float, density: float) -> tuple[float, float]:
    """(drop, add) probabilities that turn a row of this density into a copy of this similarity."""
    drop = (1 - similarity) / (1 + similarity)
    return drop, drop * density / (1 - density)
