"""Published cost formulas."""

from __future__ import annotations


def graph_ops(n: int, k: int) -> dict[str, int]:
    """Evaluations of the exact graph, of one top-K query, of all queries, and in all."""
    query = 2 * n * k - k * k + k
    return {"build": n * (n - 1), "query": query, "all_queries": n * query, "total": n * n * (2 * k + 1) + n * (k - k * k - 1)}


def hash_ops(n: int, p: int, q: int, g: int = 1, entries: int = 0) -> dict[str, int]:
    """Codes to form, and the true number of additions."""
    return {"codes": p * q * n, "additions": p * q * g * entries}


def space_bytes(method: str, n: int, p: int = 0, q: int = 0) -> int:
    """Search structure: 4 bytes a cell of the N x N graph, or a code."""
    return 0 if method == "random" else 4 * n * n if method == "graph" else 4 * n * p * q


def packed_space_bytes(n: int, p: int, q: int, g: int = 8) -> int:
    """What this package stores: g bits a code."""
    return n * p * q * ((g + 7) // 8)


def model_cells(entries: int, m: int, n: int, f: int, k: int) -> int:
    return entries + m * f + n * f + 3 * n * k


def model_params(model: str, m: int, n: int, f: int, k: int = 0, layers: tuple[int, ...] = ()) -> int:
    """Trainable numbers of each model, biases of dense layers included."""
    if model == "factor":
        return (m + n) * f
    if model == "blend":
        return m * (f + 1) + n * (f + 1 + 2 * k)
    if model == "net_product":
        return (m + n) * f + f + 1
    dense, size = 0, 2 * f
    for h in layers:
        dense += (size + 1) * h
        size = h
    if model == "net_mlp":
        return (m + n) * f + dense + size + 1
    if model == "net_fused":
        return 2 * (m + n) * f + dense + size + f + 1
    raise ValueError(model)
