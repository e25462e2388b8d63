"""What training costs: time, space and traffic of the global and the local model."""

from __future__ import annotations

import math
from collections.abc import Sequence


def time_units(sizes: Sequence[int]) -> float:
    """Eigen-decompositions and rotations of one dense block: sum of cubes plus side times cells. Sides may be columns here and below."""
    cells = math.prod(sizes)
    return 1.0 * sum(m * m * m + m * cells for m in sizes)


def local_time(block: Sequence[int], subarrays: int, nodes: int) -> float:
    return subarrays / nodes * time_units(block)


def space_units(sizes: Sequence[int], ranks: Sequence[int] | None = None) -> float:
    """Cells and mode covariances (and factor rows where ranks are given)."""
    out = math.prod(sizes) + sum(m * m for m in sizes)
    return 1.0 * (out + (sum(m * r for m, r in zip(sizes, ranks, strict=True)) if ranks else 0))


def traffic(array_sizes: Sequence[int], ranks: Sequence[int], nnz: int, coverage: float, touched: int) -> dict[str, float]:
    """Bytes of a round: parent factors out, changed rows back, and once the blocks' nonzeros."""
    r = max(ranks)
    return {"factors": 8.0 * sum(m * k for m, k in zip(array_sizes, ranks, strict=True)), "deltas": 1.0 * touched * (8 * r + 12), "blocks": 12.0 * coverage * nnz}


def extraction(array_sizes: Sequence[int], block: Sequence[int], subarrays: int, broadcast_limit: int = 64_000_000) -> str:
    """How to cut subarrays out: by broadcast index sets if they are few, else by joining the longest mode first."""
    return "broadcast" if 16 * subarrays * sum(block) <= broadcast_limit else f"join mode {max(range(len(array_sizes)), key=lambda k: array_sizes[k]) + 1} first"


def same_work(block: Sequence[int], total_cells: float) -> int:
    """Number of subarrays that keeps the trained cells equal across sizes."""
    return max(1, round(total_cells / math.prod(block)))
