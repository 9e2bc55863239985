"""Closed-form costs: flops, writes, passes, memory lines and the ratios that measured times are compared by."""

from __future__ import annotations

import math


def flops(method: str, n: float, q: int = 0, uv: bool = False) -> float:
    """Leading term for square matrices."""
    if method in ("qr", "cpqr", "sketch_qr"):
        return 4 / 3 * n**3 + (4 / 3 * n**3 if uv else 0)
    if method == "utv":
        return (4 + 4 * q / 3) * n**3 + (4 * n**3 if uv else 0)
    if method == "svd":
        return 8 / 3 * n**3 + (12 * n**3 if uv else 0)
    raise ValueError(method)


def write_volume(schedule: str, n: int, b: int) -> int:
    """Elements written by a factorization in blocks of b: the trailing matrix at each step, or one panel."""
    steps = range(0, n, b)
    return sum((n - s) ** 2 for s in steps) if schedule == "right" else sum(n * min(b, n - s) for s in steps)


def max_incore_n(size: int, copies: int) -> int:
    """Largest square matrix of doubles of which ``copies`` fit."""
    return math.isqrt(size // (8 * copies))


def scaled_time(seconds: float, n: int, power: int, factor: float = 1.0) -> float:
    return seconds / float(n) ** power * factor


def ratios(compute: float, io: float, real: float) -> dict:
    return {"sum": compute + io, "real_by_compute": real / compute, "compute_by_io": compute / io, "overlap": max(compute, io) / real}


def slowdown(a: float, b: float) -> float:
    return a / b


def speedup_percent(direct: float, overlapped: float) -> float:
    return 100.0 * (direct / overlapped - 1.0)


def passes(schedule: str, sketch: str, k: int, b: int) -> int:
    """Scans of a tall matrix by ``sketch_qr`` (one for the triangle; else a pass a step, with what its sketch takes besides)."""
    if schedule == "triangle":
        return 1
    p = -(-k // b)
    if schedule == "right":  # the draws are put beside A in the first pass; a step reads twice, and writes once but for the last
        return 3 * p - 1
    return 1 + p + (p - 1) * {"pullback": 2, "recompute": 1, "project": 0, "upfront": 0, "downdate": 0}[sketch]


def tall_flops(m: int, n: int, k: int, b: int, sketch: str = "project") -> float:
    """Leading flops of a left-looking partial run on m x n: sketches, panels made current, H'A and the panels' triangles."""
    total = 0.0
    for lo in range(0, k, b):
        w = min(b, k - lo)
        total += 2.0 * m * n * w  # G'A
        total += 2.0 * m * lo * w + 2.0 * m * n * w + 2.0 * m * w * w
        if lo and sketch == "pullback":
            total += 4.0 * m * lo * w
        if lo and sketch == "recompute":
            total += 2.0 * m * n * lo
    return total


def choose_regime(rows: float, n: int, k: int, memory: int = 512 << 20) -> str:
    """``triangle`` if n x n fits a task, else ``left``; ``tiles`` if even a thin n x k does not."""
    if 8 * n * n <= memory:
        return "triangle"
    return "left" if 8 * n * min(k, n) <= memory else "tiles"


def block_size(memory: int, tasks_per_executor: int, tiles_in_use: int = 4) -> int:
    """Largest multiple of 64 whose tiles fit a task's share, at most 2048."""
    b = math.isqrt(memory // (8 * tasks_per_executor * tiles_in_use)) // 64 * 64
    return max(64, min(2048, b))
