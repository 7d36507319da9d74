"""Cluster state between blocks: counts, radii, replica quotas, radius boost."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np


def radius_boost(done: int, total: int, kind: str = "power", b0: float = 4.0, p: float = 2.0) -> float:
    """Multiplier of the radii, large while few blocks are done: it falls to 1 with the last block."""
    if kind == "constant":
        return b0
    left = 1.0 - done / total
    return 1.0 + (b0 - 1.0) * (left**p if kind == "power" else (math.exp(p * left) - 1) / (math.exp(p) - 1))


@dataclass
class ClusterState:
    """One row per shard; a few numbers each, so it stays on the driver."""

    capacity: np.ndarray
    sample_share: np.ndarray
    radius2: np.ndarray  # squared, of originals; nan without any
    sample_weight: float = 1000.0
    n_orig: np.ndarray = field(default=None)
    n_repl: np.ndarray = field(default=None)
    replica_share: np.ndarray = field(default=None)
    n_left: int = 0  # originals of later blocks, for which room must remain

    def __post_init__(self):
        k = len(self.capacity)
        for name in ("n_orig", "n_repl"):
            if getattr(self, name) is None:
                setattr(self, name, np.zeros(k, np.int64))
        if self.replica_share is None:
            self.replica_share = np.zeros(k)

    @property
    def room(self) -> np.ndarray:
        return self.capacity - self.n_orig - self.n_repl

    @property
    def quota_left(self) -> np.ndarray:
        """Replicas that may still come: by the share of the room, and by what is free."""
        allowed = np.floor(self.replica_share * self.capacity + 1e-9).astype(np.int64) - self.n_repl
        quota = np.maximum(0, np.minimum(allowed, self.room))
        spare = max(0, int(self.room.sum()) - self.n_left)
        return quota if quota.sum() <= spare else quota * spare // max(int(quota.sum()), 1)

    def update(self, counts: np.ndarray, far2: np.ndarray) -> None:
        """After the originals of a block: sizes, and radii as the farthest original yet."""
        self.n_orig = self.n_orig + counts
        self.radius2 = np.fmax(self.radius2, far2)

    def refresh_quota(self, n_left: int, mode: str = "adaptive", lo: float = 0.0, hi: float = 0.5, margin: float = 1.1, fixed: float = 0.3) -> None:
        """Share of a shard open to replicas.

        ``adaptive`` keeps room for the originals still expected, by the share seen so far smoothed
        with the sample; ``density`` does so from the sample alone, once; ``fixed`` is one number.
        Dense shards expect more originals and so have the smaller share.
        """
        self.n_left = n_left
        if mode == "fixed":
            self.replica_share = np.full(len(self.capacity), fixed)
            return
        seen = self.n_orig if mode == "adaptive" else np.zeros_like(self.n_orig)
        w = self.sample_weight
        share = (seen + w * self.sample_share) / (seen.sum() + w)
        expected = share * n_left
        base = self.n_orig if mode == "adaptive" else 0
        self.replica_share = np.clip(1.0 - (base + margin * expected) / np.maximum(self.capacity, 1), lo, hi)

    def rows(self, block: int, boost: float) -> list[tuple]:
        return [
            (block, s, int(self.n_orig[s]), int(self.n_repl[s]), int(self.capacity[s]), float(self.replica_share[s]), None if np.isnan(self.radius2[s]) else float(np.sqrt(self.radius2[s])), boost)
            for s in range(len(self.capacity))
        ]


LOG_SCHEMA = "block_id int, shard_id int, n_orig bigint, n_repl bigint, capacity bigint, replica_share double, radius double, radius_boost double"
