"""Parameters of the moving-group methods."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Params:
    """``eps, min_pts``: density clusters. ``w``: window length in timestamps. A crowd has at least ``k_c``
    clusters of at least ``m_c`` objects, neighbours within Hausdorff distance ``d`` times their time gap.
    A participator is in at least ``k_p`` of a crowd's clusters, an aggregation has ``m_p`` of them in each
    cluster. Groups of adjacent windows are linked when they share the part ``m_g`` of the smaller one,
    and an evolving group spans at least ``k_g`` windows."""

    eps: float = 5.0
    min_pts: int = 3
    w: int = 6
    k_c: int = 5
    m_c: int = 3
    k_p: int = 4
    m_p: int = 3
    d: float = 5.0
    m_g: float = 0.7
    k_g: int = 3

    def __post_init__(self) -> None:
        checks = {
            "eps and d must be positive": self.eps > 0 and self.d > 0,
            "1 <= k_c <= w": 1 <= self.k_c <= self.w,
            "1 <= k_p <= w": 1 <= self.k_p <= self.w,
            "min_pts, m_c, m_p and k_g are at least 1": min(self.min_pts, self.m_c, self.m_p, self.k_g) >= 1,
            "0 < m_g <= 1": 0 < self.m_g <= 1,
        }
        for text, good in checks.items():
            if not good:
                raise ValueError(text)

    @property
    def max_gap(self) -> int:
        """The longest time gap of a link: a crowd misses at most ``w - k_c`` timestamps of its window."""
        return self.w - self.k_c + 1

    def but(self, **other: float) -> Params:
        """These parameters with some others."""
        return replace(self, **other)
