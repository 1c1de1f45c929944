"""Sketch identity: sizes, seeds and the rules that turn error targets into sizes."""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass, replace

#: Widths of the three experiment sizes, each with eight rows.
PRESET_WIDTHS = {"small": 2003, "medium": 20071, "large": 200003}
PRESET_DEPTH = 8
PRESET_EPS = {"small": 1e-3, "medium": 1e-4, "large": 1e-5}
DELTA = 0.003
#: Fixed value: batch size of the buffered construction.
BATCH = 1024
#: Version of the hash functions and of the packed form.
VERSION = 2

DEPTH_RULES = ("ln", "log2", "inverse", "fixed")
WIDTH_RULES = ("e_over_eps", "prime_2_over_eps", "fixed")


class IncompatibleSketch(ValueError):
    """Two sketches that do not share sizes and hash functions cannot be combined."""


def is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, math.isqrt(n) + 1))


def next_prime(n: int) -> int:
    """Smallest prime above n."""
    n += 1
    while not is_prime(n):
        n += 1
    return n


def depth_for(delta: float, rule: str = "ln", fixed: int = PRESET_DEPTH) -> int:
    if rule == "fixed":
        return fixed
    value = {"ln": math.log(1 / delta), "log2": math.log2(1 / delta), "inverse": 1 / delta}[rule]
    return math.ceil(value)


def width_for(eps: float, rule: str = "e_over_eps", fixed: int | None = None) -> int:
    if rule == "fixed":
        return fixed if fixed is not None else {v: PRESET_WIDTHS[k] for k, v in PRESET_EPS.items()}[eps]
    if rule == "e_over_eps":
        return math.ceil(math.e / eps)
    return next_prime(round(2 / eps))


@dataclass(frozen=True)
class SketchSpec:
    """What two sketches must share to be added: sizes, seed, hash family, how keys become items,
    the layout of the hash tables and the version of all this. Error targets are for the record."""

    depth: int = PRESET_DEPTH
    width: int = 2003
    seed: int = 42
    item_bits: int = 32
    hash_family: str = "tabulation"
    eps: float | None = None
    delta: float | None = None
    fingerprint: str = "md5"
    layout: str = "paired"
    version: int = VERSION

    def __post_init__(self):
        if self.depth < 1 or self.width < 1 or self.item_bits not in (32, 64):
            raise ValueError(f"no such sketch: {self}")

    @property
    def chars(self) -> int:
        return self.item_bits // 8

    @classmethod
    def from_error(cls, eps: float, delta: float, depth_rule: str = "ln", width_rule: str = "e_over_eps", **more) -> SketchSpec:
        return cls(depth_for(delta, depth_rule), width_for(eps, width_rule), eps=eps, delta=delta, **more)

    @classmethod
    def preset(cls, size: str, **more) -> SketchSpec:
        return cls(PRESET_DEPTH, PRESET_WIDTHS[size], eps=PRESET_EPS[size], delta=DELTA, **more)

    def delta_bound(self, eps: float | None = None) -> float:
        """Probability that an estimate is off by eps * N, by Markov's inequality row by row."""
        return (1 / ((eps or self.eps) * self.width)) ** self.depth

    def require_same(self, other: SketchSpec) -> None:
        drop = {"eps": None, "delta": None, "layout": "paired"}  # layouts hash alike
        if asdict(replace(self, **drop)) != asdict(replace(other, **drop)):
            raise IncompatibleSketch(f"{self} and {other}")
