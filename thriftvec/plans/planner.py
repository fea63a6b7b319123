"""Logical choices before a plan is built: executor of a search and size checks of what it would broadcast."""

from __future__ import annotations

from dataclasses import dataclass

LOCAL_BYTES = 512 << 20  # nodes, codes and texts that may be shipped to every task


@dataclass(frozen=True)
class SearchSpec:
    """One search: mode is interleaved, recompute, stored, pq or rerank."""

    k: int = 3
    ef: int = 60
    mode: str = "interleaved"
    alpha: float = 0.3
    alpha_base: str = "queue"
    min_fresh: int = 0
    aq_cap: int | None = None
    batch_target: int | None = 64
    rerank_n: int = 100
    metric: str = "l2"
    nprobe: int = 2
    approx: str = "pq"

    def __post_init__(self):
        if self.mode not in ("interleaved", "recompute", "stored", "pq", "rerank"):
            raise ValueError(f"unknown mode {self.mode}")
        if self.approx not in ("pq", "small_encoder", "neighbour_mean"):
            raise ValueError(f"unknown approximation {self.approx}")
        if self.ef < self.k:
            raise ValueError("ef must be at least k")
        if not 0 < self.alpha <= 1:
            raise ValueError("alpha must be in (0, 1]")


def choose(executor: str, size: int, shards: int) -> str:
    """`local` while everything a traversal reads may be shipped along, else `sharded`."""
    if executor != "auto":
        return executor
    return "local" if shards <= 1 and size <= LOCAL_BYTES else "sharded"
