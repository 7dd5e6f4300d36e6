"""Cost statements of the methods, as driver arithmetic."""

from __future__ import annotations

import math


def probe_cost(n: int, m: int) -> float:
    """Bounds of all cells and one cell's points."""
    return 2**m * (m + 1) + n / 2**m


def search_cost(n: int, d: int, m: int, k_p: int, n_key: int, k_sp: int, alpha: float, beta: float) -> dict[str, float]:
    """Terms of a search on the ring index: projection, clusters, key lookup, touched keys, verification."""
    keys = k_p * n_key
    return {"project": m * d, "parts": k_p * m, "lookup": math.log2(max(2, keys)), "keys": alpha * keys * (math.log2(max(2, keys)) + k_sp * m), "verify": beta * n * d}


def space(n: int, d: int, m: int) -> dict[str, float]:
    return {"vectors": n * d, "projections": n * m, "order": n * math.log2(max(2, n))}


def complexity(method: str) -> tuple[str, str]:
    """Time and space classes as stated for the compared methods."""
    return {"ring": ("d + n log n", "n d + n log n"), "shell_lsh": ("d log n + n log n", "n d + n log n"), "norm_band_lsh": ("d log n + n log n", "n d + n log n")}[method]
