"""Settings of the resolution methods."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Config:
    vote_mode: str = "ratio"  # or "majority", "fixed_accuracy"
    accuracy: float = 0.9
    eps: float = 1e-9  # stands for a score of zero
    samples: int = 1000
    exact_max_edges: int = 18
    walk: str = "all"  # sampled worlds draw all edges; "bfs" draws those that a walk from one record meets
    exact_gain_edges: int = 8  # clusters of so few edges have exact gains
    batch: int = 1
    pair_sample: int | None = None  # unasked pairs of a cluster that are judged, in hash order; None: all
    across_per_pair: int = 1  # questions of one pair of clusters in a batch
    edgeless: str = "first"  # or "skip"
    initial: int | str = 0  # pairs, "none", "spanning" or "all"
    budget: int | None = None
    target_f1: float | None = None
    merge_threshold: float = 0.5
    scc_mode: str = "contract"  # or "exact", without parallel contraction; "rounds", approximate
    max_component: int = 2_000_000  # edges that a task merges at a time: about 400 bytes each
    recheck: str = "on_disagreement"  # or "always"
    seed: int = 42
