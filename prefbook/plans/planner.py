"""Where a design problem is solved, and what follows from its size.

A problem whose types (items of equal SPV) fit a bounded table is solved run by run inside
tasks: the table is sent once, and the runs of a sweep over books, pools and restarts are
spread over the cluster. A larger problem is solved by passes over its table, all runs in
each pass.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefbook.operators.dcdescent import descend
from prefbook.operators.refine import Design, Run, refine
from prefbook.operators.spv import collapse_types
from prefbook.plans.engine import UNROLLED, LocalEngine, SparkEngine

#: Problems that are sent to the tasks at once, and tasks of a sweep.
PROBLEMS, TASKS = 16, 4096
METHODS: dict[str, Callable[..., list[Design]]] = {"refine": refine, "dc": descend}


@dataclass(frozen=True)
class Limits:
    """A problem of at most so many numbers is sent to the tasks: 16 MB."""

    cells: int = 2_000_000


@dataclass(frozen=True)
class Choice:
    strategy: str
    reason: str


def choose(types: DataFrame, n: int, books: int, limits: Limits = Limits()) -> Choice:
    most = limits.cells // (n + 4)
    if types.limit(most + 1).count() <= most:
        return Choice("runs in tasks", f"at most {most} types of {n} symbols")
    wide = books * n > UNROLLED
    return Choice("passes over blocks" if wide else "passes by expressions", f"more than {most} types; {books} books of {n} symbols {'exceed' if wide else 'fit'} generated code")


def as_problem(items: DataFrame) -> DataFrame:
    """item_id, p and weights; a demand f is the weight of the common channel."""
    if "w0" in items.columns:
        return items.select("item_id", "p", *(c for c in ("w0", "w1", "w2") if c in items.columns))
    return items.select("item_id", "p", F.col("f").alias("w0"))


def solve(items: DataFrame, n: int, runs: list[Run], method: str = "refine", strategy: str | None = None, limits: Limits = Limits(), **options) -> list[Design]:
    """Designs of all runs over ``items`` (item_id, p and f or w0, w1, w2)."""
    types = collapse_types(as_problem(items)).persist()
    try:
        books = max(r.layout.books for r in runs)
        where = strategy or choose(types, n, books, limits).strategy
        if where == "runs in tasks":
            return _in_tasks({0: types}, n, runs, method, options)[0]
        engine = SparkEngine(types, n)
        try:
            return METHODS[method](engine, runs, **options)
        finally:
            engine.release()
    finally:
        types.unpersist()


def sweep(problems: dict[Any, DataFrame], n: int, runs: list[Run], method: str = "refine", limits: Limits = Limits(), **options) -> dict[Any, list[Design]]:
    """Designs of all runs over each of several problems; those of bounded size are solved side by side by one job."""
    books = max(r.layout.books for r in runs)
    small, out = {}, {}
    for key, items in problems.items():
        types = collapse_types(as_problem(items)).persist()
        if choose(types, n, books, limits).strategy == "runs in tasks":
            small[key] = types
        else:
            types.unpersist()
            out[key] = solve(items, n, runs, method, None, limits, **options)
    names = list(small)
    for at in range(0, len(names), PROBLEMS):
        out |= _in_tasks({k: small[k] for k in names[at : at + PROBLEMS]}, n, runs, method, options)
    for types in small.values():
        types.unpersist()
    return {key: out[key] for key in problems}


def local_engine(types: DataFrame, n: int) -> LocalEngine:
    """The table as arrays; its size has been checked."""
    frame = types.orderBy("item_id").toArrow()
    rows = frame.num_rows
    p = np.array(frame.column("p").combine_chunks().flatten().to_numpy(zero_copy_only=False)).reshape(rows, n) if rows else np.zeros((0, n))
    w = np.zeros((rows, 3))
    for i, c in enumerate(("w0", "w1", "w2")):
        if c in frame.column_names:
            w[:, i] = frame.column(c).to_numpy()
    return LocalEngine(frame.column("item_id").to_numpy(), p, w)


def _in_tasks(problems: dict[Any, DataFrame], n: int, runs: list[Run], method: str, options: dict) -> dict[Any, list[Design]]:
    engines = {key: local_engine(types, n) for key, types in problems.items()}
    keys = [k for k, e in engines.items() if len(e.ids)]
    out = {k: [Design(r, np.full((r.layout.books, n), 1.0 / n), 0.0) for r in runs] for k in problems}
    if not keys:
        return out
    spark = problems[keys[0]].sparkSession
    sent = spark.sparkContext.broadcast(([(engines[k].ids, engines[k].p, engines[k].w) for k in keys], {r.run_id: r for r in runs}))
    solver = METHODS[method]

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tables, asked = sent.value
        for frame in frames:
            for problem, k in zip(frame["problem"], frame["run_id"]):
                d = solver(LocalEngine(*tables[problem]), [asked[k]], **options)[0]
                yield pd.DataFrame({"problem": [problem], "run_id": [k], "q": [d.q.ravel().tolist()], "cost": [d.cost], "steps": [[x[0] for x in d.trace]], "values": [[x[1] for x in d.trace]], "seconds": [[x[2] for x in d.trace]], "used": [d.used.tolist()]})

    # Large runs first, one to a task, so that no task is left with several of them at the end.
    jobs = sorted(((i, r.run_id, -r.layout.books) for i in range(len(keys)) for r in runs), key=lambda x: x[2])
    asked = spark.createDataFrame([(k, i, r) for k, (i, r, _) in enumerate(jobs)], "place int, problem int, run_id int").repartitionByRange(min(len(jobs), TASKS), "place").drop("place")
    found = {(r["problem"], r["run_id"]): r for r in asked.mapInPandas(work, "problem int, run_id int, q array<double>, cost double, steps array<int>, values array<double>, seconds array<double>, used array<boolean>").collect()}
    for i, key in enumerate(keys):
        out[key] = [Design(r, np.array(x["q"]).reshape(-1, n), x["cost"], list(zip(x["steps"], x["values"], x["seconds"])), np.array(x["used"])) for r in runs for x in [found[i, r.run_id]]]
    return out


def best_of(designs: list[Design]) -> Design:
    return min(designs, key=lambda d: (d.cost, d.run.run_id))
