"""Descent on the soft assignment by a difference of convex functions.

With t the weight that a book gets and s its weighted sum of SPVs, the cost of the best
books for given soft shares is sum t log t - sum s log s. The second part is replaced by
its tangent, and what is left is minimised over the shares by multiplicative steps. After
any number of steps the shares are proportional to 2 ** (noise + p . b - a), with b the
sum of the tangents' slopes and a that of log t, so no share is ever stored: the state of
a run is books x (symbols + 1) numbers.
"""

from __future__ import annotations

import time

import numpy as np

from prefbook.operators.refine import Design, Run, means
from prefbook.plans.engine import Sums
from prefbook.schemas import TOLERANCE

FLOOR = 1e-300


def _xlogx(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x * np.log2(np.maximum(x, FLOOR)), 0.0)


def split(sums: Sums) -> tuple[float, float]:
    """Values of the two convex parts."""
    return float(_xlogx(sums.t).sum()), float(_xlogx(sums.s).sum())


def objective(sums: Sums) -> float:
    convex, concave = split(sums)
    return convex - concave


def surrogate(sums: Sums, slope: np.ndarray) -> float:
    """What an inner solve lowers: the first part less the tangent of the second, up to a constant."""
    return split(sums)[0] - float((slope * sums.s).sum())


def slopes(sums: Sums) -> np.ndarray:
    """Gradient of the second part, up to a constant that all shares feel alike."""
    return np.log2(np.maximum(sums.s, FLOOR))


def descend(engine, runs: list[Run], eps: float = TOLERANCE, inner: int = 5, outer: int = 100_000, rounding: str = "nearest", fixed: bool = False) -> list[Design]:
    """Designs of all runs. ``rounding``: 'argmax' gives each item to its likeliest book, 'nearest' to its cheapest, which is never worse.

    A run ends when the objective falls by no more than ``eps`` in an outer step. An inner solve ends after ``inner``
    steps or where one lowers its convex problem by no more than a hundredth of ``eps``; ``fixed``: exactly so many steps.
    """
    n = engine.n
    state = {r.run_id: (r.layout, r.seed, np.zeros(r.layout.books), np.zeros((r.layout.books, n))) for r in runs}
    designs = {r.run_id: Design(r, np.zeros((r.layout.books, n))) for r in runs}
    active = {r.run_id for r in runs}
    now = engine.soft(state)
    for k in active:
        designs[k].trace.append((0, objective(now[k]), 0.0))
    for i in range(1, outer + 1):
        if not active:
            break
        began = time.time()
        slope = {k: slopes(now[k]) for k in active}
        left = {k: surrogate(now[k], slope[k]) for k in active}
        for _ in range(inner):
            for k in left:
                layout, seed, a, b = state[k]
                state[k] = (layout, seed, a + np.log2(np.maximum(now[k].t, FLOOR)), b + slope[k])
            now |= engine.soft({k: state[k] for k in left})
            value = {k: surrogate(now[k], slope[k]) for k in left}
            left = {k: value[k] for k in left if fixed or left[k] - value[k] > eps / 100}
            if not left:
                break
        for k in list(active):
            value = objective(now[k])
            drop = designs[k].trace[-1][1] - value
            designs[k].trace.append((i, value, time.time() - began))
            if not fixed and drop <= eps:
                active.discard(k)
    soft = {k: means(now[k], np.full_like(now[k].s, 1.0 / n)) for k in designs}
    if rounding == "argmax":
        hard = engine.rounded(state)
        books = {k: means(hard[k], soft[k]) for k in designs}
    else:
        passed = engine.hard({k: (designs[k].run.layout, soft[k]) for k in designs})
        books = {k: means(passed[k], soft[k]) for k in designs}
    final = engine.hard({k: (designs[k].run.layout, books[k]) for k in designs})
    for k, d in designs.items():
        d.q, d.cost, d.used = books[k], float(final[k].cost.sum()), final[k].t > 0
    return [designs[r.run_id] for r in runs]
