"""Physical choices by the size of the input."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Plan:
    labels: str  # world: one task a world; edge: stars over (world, node)
    fast_draws: bool  # xxhash64 instead of md5
    block: int  # centers decided at a time
    disks: str  # driver, join or sampled


def choose(n: int, m: int, r: int, q: float, portable: bool = False, task_edges: int = 100_000_000, broadcast_bytes: int = 256 << 20) -> Plan:
    """How to label worlds, draw edges and find disks on a graph of n nodes and m edges with r worlds at threshold q.

    A world's live edges must fit in a task for the world strategy; a block's signatures must fit in a broadcast."""
    block = max(1, min(64, broadcast_bytes // max(1, 8 * r)))
    disks = "driver" if n * n * (1 - q) <= 2_000_000 else "join"
    return Plan("world" if m <= task_edges else "edge", not portable, block, disks)
