"""Costs: backbone calls and rows, free of hardware, and driver-clock timings."""

from __future__ import annotations

import time


def counters(m: int, g: int, s: int, h: int, n: int, d: int) -> tuple:
    """(tasks, candidates, folds, fold size, fit calls, fit rows, rows scored, rows of the attribute chain, attributes)."""
    return m, g, s, h, m * g * s, m * g * s * 2 * h, m * n, d * n, d


def timed(f, *a, **k) -> tuple[float, object]:
    t = time.perf_counter()
    out = f(*a, **k)
    return time.perf_counter() - t, out
