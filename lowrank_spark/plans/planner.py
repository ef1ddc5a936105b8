"""Choices between physical forms, as pure functions of sizes."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Sizes:
    m: int
    n: int
    entries: int
    row_degree_sq: int = 0  # sum of squared row degrees
    executors: int = 1
    task_bytes: int = 1 << 30
    broadcast_bytes: int = 64 << 20


def choose_topk(s: Sizes, pair_budget: int) -> str:
    """exact while the co-rated join is affordable, else hash."""
    return "exact" if s.row_degree_sq / 2 <= pair_budget else "hash"


def sgd_bytes(s: Sizes, f: int, k: int, d: int) -> dict[str, float]:
    """Bytes moved per epoch by each form."""
    return {
        "broadcast": s.n * (f + 2 * k + 1) * 4.0 * s.executors,
        "rotation": d * s.m * (f + 1) * 4.0,
        "gather": 2.0 * s.entries * (f + 1) * 4.0,
    }


def choose_sgd(s: Sizes, f: int, k: int, d: int) -> str:
    """The cheapest form that is allowed: column state must fit a broadcast, a row block must fit a task."""
    cost = sgd_bytes(s, f, k, d)
    if s.n * (f + 2 * k + 1) * 4 > s.broadcast_bytes:
        cost.pop("broadcast")
    if s.m / d * (f + 1) * 4 > s.task_bytes:
        cost.pop("rotation")
    return min(cost, key=cost.get)


def sums_form(entries_per_column_and_task: float, lanes: int) -> str:
    """combine map-side only when a column's entries in a task outweigh its vector of lanes."""
    return "combine" if entries_per_column_and_task > 8 * lanes / 16 else "gather"
