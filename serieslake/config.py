"""One frozen set of parameters for building and asking an index."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class IndexConfig:
    n: int = 64  #: points of a series
    w: int = 8  #: segments of a summary
    bits: int = 8  #: bits of a symbol
    theta: int = 16  #: items a leaf holds before it splits
    queues: int = 4
    split_policy: str = "round_robin"  #: or "balanced"
    mode: str = "leaf"  #: or "subtree", "standard", "private": how concurrent tree work commits
    strategy: str = "helping"
    seed_how: str = "leaf"  #: or "best_lb", "none": where the first best-so-far comes from
    waves: str = "geometric"  #: or "one"
    levels: int = 3
    k_chunks: int = 8
    m_groups: int = 4
    backoff_factor: float = 1.0
    slack: float = 1e-9  #: a bound prunes only beyond this relative margin
    normalise: str = "z"  #: or "none"

    @property
    def max_depth(self) -> int:
        return self.w * (self.bits - 1)
