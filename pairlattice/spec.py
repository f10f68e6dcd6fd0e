"""Options of the estimators."""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import comb


@dataclass(frozen=True)
class EstimatorSpec:
    """What to estimate and how.

    ``ratio`` is the share of sub-values kept per record and level, one number or one per level.
    ``sampler``: ``fixed`` draws a fixed number of subsets per record and level (rounded at random),
    ``bernoulli`` keeps each with the ratio's chance, ``replacement`` draws with replacement (an
    ablation: its self-pairs are wrong, so its estimates are biased).
    ``fingerprint``: ``xx64``, ``md5_60`` (the same in every engine) or ``raw`` (no collisions).
    ``null_policy``: ``equal`` (null matches null), ``never`` (a sub-value with a null matches
    nothing), ``drop`` (complete records only).
    ``self_pairs``: subtract the ``emitted`` number of sub-values, or the ``expected`` one.
    ``clamp``: ``none`` (unbiased), ``final`` (negative levels become 0 at the end), ``cascade``
    (they become 0 before lower levels are solved).
    """

    s: int
    ratio: float | dict = 1.0
    sampler: str = "fixed"
    fingerprint: str = "xx64"
    null_policy: str = "equal"
    self_pairs: str = "emitted"
    clamp: str = "none"
    pair_counting: str = "ordered"
    width: int = 1000
    depth: int = 3
    combine: str = "median"
    kind: str = "fast"
    seed: int = 7

    def check(self, d: int) -> EstimatorSpec:
        if not 1 <= self.s <= d:
            raise ValueError(f"threshold {self.s} is not within 1..{d}; threshold 0 needs no estimate, it is n * n")
        if d > 20:
            raise ValueError(f"{d} attributes have 2^{d} subsets; choose fewer attributes first")
        for k in range(self.s, d + 1):
            if not 0 < self.ratio_of(k) <= 1:
                raise ValueError(f"ratio {self.ratio_of(k)} of level {k} is not within (0, 1]")
        allowed = {"sampler": ("fixed", "bernoulli", "replacement"), "fingerprint": ("xx64", "md5_60", "raw"), "null_policy": ("equal", "never", "drop"), "self_pairs": ("emitted", "expected"), "clamp": ("none", "final", "cascade"), "pair_counting": ("ordered", "unordered"), "combine": ("median", "mean"), "kind": ("fast", "plain")}
        for name, values in allowed.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} is one of {values}")
        if self.null_policy == "never" and self.self_pairs == "expected":
            raise ValueError("with null_policy never the number of self-pairs is not known; use emitted")
        if self.width < 1 or self.depth < 1:
            raise ValueError("width and depth are at least 1")
        return self

    def ratio_of(self, level: int) -> float:
        return float(self.ratio[level] if isinstance(self.ratio, dict) else self.ratio)

    def with_(self, **kw) -> EstimatorSpec:
        return replace(self, **kw)


def sub_values(d: int, s: int) -> int:
    """Sub-values of a record at ratio 1: subsets with at least ``s`` of ``d`` attributes."""
    return sum(comb(d, k) for k in range(s, d + 1))
