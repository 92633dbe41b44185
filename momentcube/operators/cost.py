"""Cost measures: time of merges, estimates and queries, and the model that adds them up."""

from __future__ import annotations

import time

import numpy as np

from ..functions import maxent, sketches


def merge_seconds(kind: str, cells: list[np.ndarray], repeat: int = 3) -> float:
    """Seconds for one merge on one thread; kind "moments" or one of the sketches."""
    best = float("inf")
    for _ in range(repeat):
        if kind == "moments":
            states = [np.concatenate([[len(x), x.min(), x.max()], [(x**i).sum() for i in range(1, 11)]]) for x in cells]
            began, acc = time.perf_counter(), states[0].copy()
            for s in states[1:]:
                lo, hi = min(acc[1], s[1]), max(acc[2], s[2])
                acc += s
                acc[1], acc[2] = lo, hi
        else:
            impl = sketches.KINDS[kind]
            states = [impl.build(x) for x in cells]
            began = time.perf_counter()
            acc = states[0]
            for s in states[1:]:
                acc = impl.merge(acc, s)
        best = min(best, (time.perf_counter() - began) / max(len(cells) - 1, 1))
    return best


def estimate_seconds(batch: maxent.Batch, phis=(0.5,), solver: str = "chebyshev") -> float:
    began = time.perf_counter()
    maxent.quantiles(batch, phis, solver)
    return (time.perf_counter() - began) / len(batch.n)


def model(n_merge: int, t_merge: float, n_groups: int, t_est: float) -> float:
    """Merging and estimating, one after the other."""
    return n_merge * t_merge + n_groups * t_est


def crossover(t_merge: float, t_est: float) -> float:
    """Number of merges at which merging costs as much as one estimate."""
    return t_est / t_merge
