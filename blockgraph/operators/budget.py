"""Arithmetic of blocks, segments and memory."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class Geometry:
    vertex_kb: float
    block_cap: int
    n_blocks: int


def block_geometry(n: int, dim: int, elem_bytes: int, max_degree: int, block_kb: float = 4) -> Geometry:
    """Record of a vertex (values, degree, padded neighbour ids), vertices in a
    block, blocks of n vertices."""
    vertex_kb = (dim * elem_bytes + 4 + 4 * max_degree) / 1024
    cap = int(block_kb / vertex_kb)
    if cap < 1:
        raise ValueError("a vertex does not fit a block")
    return Geometry(vertex_kb, cap, math.ceil(n / cap))


def segment_capacity(disk_gb: float, dim: int, elem_bytes: int, max_degree: int, block_kb: float = 4) -> int:
    """Most vertices whose blocks fit the disk."""
    cap = block_geometry(1, dim, elem_bytes, max_degree, block_kb).block_cap
    return int(disk_gb * 2**20 // block_kb) * cap


def fit_degree(n: int, disk_gb: float, dim: int, elem_bytes: int, block_kb: float = 4, most: int = 128) -> int:
    """Largest degree for which n vertices fit the disk (0 if none does)."""
    for degree in range(most, 0, -1):
        try:
            g = block_geometry(n, dim, elem_bytes, degree, block_kb)
        except ValueError:
            continue
        if g.n_blocks * block_kb <= disk_gb * 2**20:
            return degree
    return 0


def fit_navigator(n: int, memory_gb: float, dim: int, elem_bytes: int, most: float = 0.1, degrees=(48, 32, 20, 10)) -> tuple[float, int]:
    """Sample ratio and degree of a navigator that fits the memory."""
    for degree in degrees:
        ratio = memory_gb * 2**30 / (n * (dim * elem_bytes + 4 + 4 * degree))
        if ratio >= most / 2 or degree == degrees[-1]:
            return min(most, ratio), degree
    raise AssertionError


def pq_bytes_per_vector(budget_gb: float, n: int) -> float:
    return budget_gb * 2**30 / n


def disk_bytes(n_blocks: int, block_kb: float = 4) -> int:
    """The same before and after shuffling: the order alone changes."""
    return int(n_blocks * block_kb * 1024)


def memory_bytes(n: int, dim: int, elem_bytes: int, sample: int, nav_degree: int, code_bytes: int, shuffled: bool = True) -> dict[str, int]:
    """Navigator, id-to-block map (only needed once shuffled) and codes."""
    return {"navigator": sample * (dim * elem_bytes + 4 + 4 * nav_degree), "mapping": 4 * n if shuffled else 0, "codes": n * code_bytes}


def io_model(degree: float, path: float, utilisation: float, cap: int) -> float:
    """Expected block reads without codes: o * l / (xi * eps)."""
    return degree * path / (utilisation * cap)
