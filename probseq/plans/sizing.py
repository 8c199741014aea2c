"""Arithmetic of a run at scale: what a pass reads, shuffles and holds."""

from __future__ import annotations

from dataclasses import dataclass

NODE_BYTES = 40  # parent, kind, item and sums of a tree node
PARTIAL_BYTES = 40  # a partial sum of one live extension


@dataclass(frozen=True)
class PassSize:
    tasks: int
    scan_bytes: int
    shuffle_bytes: int
    tree_bytes: int
    tree_fits: bool


def level_pass(data_bytes: int, split_bytes: int, live_extensions: int, nodes: int, tree_budget: int = 256 << 20) -> PassSize:
    """A growth pass over packed sequences: tasks, and at most one partial row per task and live extension."""
    tasks = max(1, -(-data_bytes // split_bytes))
    tree = nodes * NODE_BYTES
    return PassSize(tasks, data_bytes, tasks * live_extensions * PARTIAL_BYTES, tree, tree <= tree_budget)


def split_for(data_bytes: int, live_extensions: int, shuffle_budget: int, least: int = 128 << 20, most: int = 2 << 30) -> int:
    """The smallest split that keeps the partial sums of a pass within a budget."""
    split = least
    while split < most and level_pass(data_bytes, split, live_extensions, 0).shuffle_bytes > shuffle_budget:
        split *= 2
    return split
