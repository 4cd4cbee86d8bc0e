"""Alternating design: each item turns to its cheapest book, each book becomes the mean of its items.

One rule serves one user and two: books belong to pools, channels may use the common pool
and their own. Seeds are drawn by weight and by a power of the divergence to the seeds so
far, the common pool first.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from prefbook.plans.engine import Draw, Layout, LocalEngine, Sums
from prefbook.schemas import TOLERANCE


@dataclass(frozen=True)
class Run:
    run_id: int
    layout: Layout
    seed: int = 1


@dataclass
class Design:
    """Books in the order of their pools, cost in bits per symbol (summed over weights), and the trace of costs."""

    run: Run
    q: np.ndarray
    cost: float = float("inf")
    trace: list[tuple[int, float, float]] = field(default_factory=list)
    used: np.ndarray | None = None


def seed_books(engine, runs: list[Run], power: float = 2.0, mix: float = 0.0) -> dict[int, np.ndarray]:
    """Seeds of every run, one draw of all runs a pass. With fewer distinct SPVs than books the mean fills up."""
    chosen: dict[int, list[np.ndarray]] = {r.run_id: [] for r in runs}
    mean = None
    for turn in range(max(r.layout.books for r in runs)):
        draws = []
        for r in runs:
            if turn < r.layout.books:
                pool = int(r.layout.pools[turn])
                near = [q for q, own in zip(chosen[r.run_id], r.layout.pools) if own in (0, pool)]
                draws.append(Draw(r.run_id, r.seed, turn + 1, pool, power, np.array(near)))
        won = engine.draw(draws)
        for d in draws:
            if d.run_id not in won:
                mean = engine.mean() if mean is None else mean
            chosen[d.run_id].append(won.get(d.run_id, mean))
    if mix:
        mean = engine.mean() if mean is None else mean
        return {r: np.array([(1 - mix) * q + mix * mean for q in books]) for r, books in chosen.items()}
    return {r: np.array(books) for r, books in chosen.items()}


def seed_parallel(engine, run: Run, rounds: int = 3, factor: float = 2.0, power: float = 1.0) -> np.ndarray:
    """Seeds of a single-user run by oversampling: each round keeps every item with a chance by its share of the cost.

    A round is two passes whatever the number of books; the few candidates are weighed by the items nearest to them
    and cut down to the books asked for on the driver.
    """
    k = run.layout.books
    found = [engine.draw([Draw(run.run_id, run.seed, 1, 0, power, np.zeros((0, engine.n)))]).get(run.run_id, engine.mean())]
    for turn in range(rounds):
        found += engine.oversample(np.array(found), run.seed, 500 + turn, factor * k, power)
    candidates = np.unique(np.array(found), axis=0)
    smooth = 0.999 * candidates + 0.001 * engine.mean()
    weight = engine.hard({run.run_id: (Layout(len(candidates)), smooth)})[run.run_id].t
    local = LocalEngine(np.arange(len(candidates)), candidates, np.column_stack([weight, np.zeros((len(weight), 2))]))
    return seed_books(local, [run], power)[run.run_id]


def means(sums: Sums, q: np.ndarray) -> np.ndarray:
    """New books; a book without items stays as it is."""
    total = sums.s.sum(axis=1, keepdims=True)
    return np.where(total > 0, sums.s / np.where(total > 0, total, 1.0), q)


def refine(engine, runs: list[Run], iterations: int = 100, eps: float = TOLERANCE, power: float = 2.0, mix: float = 0.0, start: dict[int, np.ndarray] | None = None, fixed: bool = False, seeding: str = "plusplus", stop: str = "either") -> list[Design]:
    """Designs of all runs, one pass for all of them an iteration; ``fixed``: exactly that many updates.

    ``stop`` says when a run ends: 'cost', when its cost falls by no more than ``eps``; 'books', when the fixed-point
    equations hold, that is no share of any book moves by more than ``eps``; 'either', at the first of the two.
    """
    if stop not in ("cost", "books", "either"):
        raise ValueError(stop)
    q = start or ({r.run_id: seed_parallel(engine, r) for r in runs} if seeding == "parallel" else seed_books(engine, runs, power, mix))
    designs = {r.run_id: Design(r, q[r.run_id]) for r in runs}
    active = {r.run_id: r for r in runs}
    for i in range(iterations + 1):
        if not active:
            break
        began = time.time()
        passed = engine.hard({k: (r.layout, designs[k].q) for k, r in active.items()})
        for k, r in list(active.items()):
            d, sums = designs[k], passed[k]
            cost = float(sums.cost.sum())
            d.trace.append((i, cost, time.time() - began))
            moved = means(sums, d.q)
            still = stop != "books" and i > 0 and d.cost - cost <= eps
            settled = stop != "cost" and float(np.abs(moved - d.q).max()) <= (eps if stop == "books" else 0.0)
            done = i == iterations or (not fixed and (still or settled or np.array_equal(moved, d.q)))
            d.cost, d.used = cost, sums.t > 0
            if done:
                del active[k]
            else:
                d.q = moved
    return [designs[r.run_id] for r in runs]
