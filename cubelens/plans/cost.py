"""Sizes and transfers of the cube strategies, and the choice among them."""

from __future__ import annotations

from math import comb

#: Bytes of dense cells that a task of the local strategy holds at once.
LOCAL_BYTES = 512 << 20


def footprint(n: int, bins: int, cell_bytes: int = 8, arity: int = 3) -> tuple[int, int]:
    """Cells and bytes of all aggregates of ``arity`` dimensions."""
    cells = comb(n, arity) * bins**arity
    return cells, cells * cell_bytes


def suggest_bins(n: int, memory_bytes: int, cell_bytes: int = 8, choices=(16, 32, 64, 128, 256)) -> int:
    """The finest resolution whose cubes fit; doubling it costs eight times the space."""
    fit = [b for b in choices if footprint(n, b, cell_bytes)[1] <= memory_bytes]
    return max(fit, default=min(choices))


def row_copies(strategy: str, n: int, owners: int | None = None, units: int = 1) -> int:
    """How often a row is updated or sent."""
    if strategy in ("expand", "explode", "per_triple", "local_dense"):
        return comb(n, 3)
    if strategy == "by_triple":
        return units
    return n


def shuffled_bytes(strategy: str, rows: int, n: int, bins: int, tasks: int) -> float:
    """Bytes through exchanges, after partial aggregation by ``tasks`` input tasks."""
    triples, row = comb(n, 3), n + 8
    if strategy in ("expand", "explode"):
        return min(rows, tasks * bins**3) * triples * 24.0
    if strategy == "per_triple":
        return triples * min(rows, tasks * bins**3) * 16.0
    if strategy == "owner_slice":
        return float(rows) * n * row
    return tasks * triples * min(bins**3, max(rows // max(tasks, 1), 1)) * 20.0


def scans(strategy: str, n: int, bins: int, parts: int = 1, memory: int = LOCAL_BYTES) -> int:
    if strategy == "per_triple":
        return comb(n, 3) * parts
    if strategy == "local_dense":
        return max(1, -(-footprint(n, bins)[1] // memory))
    return 1


def choose_strategy(rows: int, n: int, bins: int, tasks: int, memory: int = LOCAL_BYTES) -> str:
    """The cheapest by bytes moved plus bytes scanned; grouping sets only for few triples. ``tasks`` read the input."""
    row = n + 8
    options = ["owner_slice", "local_dense"] + (["explode"] if comb(n, 3) <= 60 else []) + (["per_triple"] if comb(n, 3) <= 20 else [])
    price = {s: shuffled_bytes(s, rows, n, bins, tasks) * 3 + scans(s, n, bins, memory=memory) * rows * row * (4 / n if s == "per_triple" else 1) for s in options}
    return min(options, key=price.get)
