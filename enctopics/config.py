"""Settings of the clustering schemes."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Config:
    keywords_per_doc: int = 10
    trim: str | int = "mean"
    inclusive: bool = False  # uniqueness of exactly 1 counts
    zero_overlap: str = "unit"  # or "infinite": what a token without covered documents is worth
    disparity: str = "literal"  # or "off", "symmetric"
    orphan: str = "cooccurring_only"  # or "literal"
    abstract_size: int = 10
    probed_clusters: int = 3
    alpha: float = 0.05
    dof: int = 1
    cells: str = "single"  # or "pair"
    unit: float | None = None
    theta_initial: float = 0.1
    tsap_n: int = 10
    runs: int = 10
    fixed_k: int = 10
    samplings: int = 10
    confidence: float = 0.95
    broadcast_rows: int = 2_000_000  # a side is broadcast only if it was counted and is no larger
    key: str = "fixture-key"
