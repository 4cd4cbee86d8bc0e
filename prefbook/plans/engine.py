"""The two ways to make a pass over the items of a design problem.

Designs need three kinds of pass: weighted sums over nearest books, over soft shares, and
a weighted draw. All state between passes is a few numbers per book on the driver.

``SparkEngine`` makes each pass a job over the items table: nearest books as straight-line
expressions for few books and symbols, as matrix products of Arrow blocks for many; soft
shares always as matrix products. Only sums per book cross the network.

``LocalEngine`` holds a problem of bounded size as arrays, so that many runs can be solved
side by side, each within one task. Both give the same numbers up to rounding.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefbook.functions.info import cost_unrolled, entropy_bits, entropy_unrolled
from prefbook.functions.uniform import hash_uniform, uniform

#: Books times symbols up to which a pass is generated as straight-line code.
UNROLLED = 100
#: Symbols up to which sums over a vector are separate columns.
WIDE = 16
#: First draw number of the noise that soft shares start from.
NOISE_DRAW = 1000


@dataclass(frozen=True)
class Layout:
    """Sizes of the pools: common books, books of user 1 alone, of user 2 alone. A single user has common books only."""

    k0: int
    k1: int = 0
    k2: int = 0

    @property
    def pools(self) -> np.ndarray:
        return np.repeat([0, 1, 2], [self.k0, self.k1, self.k2])

    @property
    def books(self) -> int:
        return self.k0 + self.k1 + self.k2

    def allowed(self, channel: int) -> np.ndarray:
        return (self.pools == 0) | (self.pools == channel)


@dataclass
class Sums:
    """Per book: total weight, weighted sum of SPVs, and weighted cost in bits per symbol."""

    t: np.ndarray
    s: np.ndarray
    cost: np.ndarray


@dataclass
class Draw:
    """One weighted draw of a run: by the weight of a pool, times a power of the divergence to the books so far."""

    run_id: int
    seed: int
    draw: int
    pool: int
    power: float
    books: np.ndarray


def code_bits(q: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore"):
        return -np.log2(q)


def cross(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Bits per symbol of each row of p under each row of q."""
    bits = code_bits(q)
    finite = np.where(np.isfinite(bits), bits, 0.0)
    cost = p @ finite.T
    zero = ~np.isfinite(bits)
    if zero.any():
        cost[(p > 0).astype(float) @ zero.T.astype(float) > 0] = np.inf
    return cost


def hard_block(p: np.ndarray, w: np.ndarray, layout: Layout, q: np.ndarray) -> Sums:
    """Sums over nearest books; requests of a channel that no book serves cost infinitely much."""
    costs = cross(p, q)
    out = Sums(np.zeros(layout.books), np.zeros((layout.books, p.shape[1])), np.zeros(layout.books))
    for channel in range(3):
        use = np.flatnonzero(w[:, channel] > 0)
        names = np.flatnonzero(layout.allowed(channel))
        if not len(use):
            continue
        if not len(names):
            out.cost[0] = np.inf
            continue
        own = costs[np.ix_(use, names)]
        best = own.argmin(axis=1)
        weight = w[use, channel]
        chosen = names[best]
        out.t += np.bincount(chosen, weights=weight, minlength=layout.books)
        out.cost += np.bincount(chosen, weights=weight * own[np.arange(len(use)), best], minlength=layout.books)
        share = np.zeros((len(use), layout.books))
        share[np.arange(len(use)), chosen] = weight
        out.s += share.T @ p[use]
    return out


def soft_shares(p: np.ndarray, noise: np.ndarray, layout: Layout, a: np.ndarray, b: np.ndarray, channel: int) -> np.ndarray:
    """Probabilities proportional to 2 ** (noise + p . b - a) over the books that a channel may use."""
    logits = p @ b.T - a + noise[:, : layout.books]
    logits[:, ~layout.allowed(channel)] = -np.inf
    logits -= logits.max(axis=1, keepdims=True)
    shares = np.exp2(logits)
    return shares / shares.sum(axis=1, keepdims=True)


def soft_block(p: np.ndarray, w: np.ndarray, noise: np.ndarray, layout: Layout, a: np.ndarray, b: np.ndarray) -> Sums:
    out = Sums(np.zeros(layout.books), np.zeros((layout.books, p.shape[1])), np.zeros(layout.books))
    for channel in range(3):
        use = np.flatnonzero(w[:, channel] > 0)
        if len(use) and layout.allowed(channel).any():
            shares = soft_shares(p[use], noise[use], layout, a, b, channel) * w[use, channel : channel + 1]
            out.t += shares.sum(axis=0)
            out.s += shares.T @ p[use]
    return out


def pool_weight(w: np.ndarray, pool: int) -> np.ndarray:
    """What an item weighs when a book of a pool is drawn; a user without lone requests falls back on all."""
    total = w.sum(axis=1)
    return w[:, pool] if pool and w[:, pool].sum() > 0 else total


class LocalEngine:
    def __init__(self, ids: np.ndarray, p: np.ndarray, w: np.ndarray):
        self.ids, self.p, self.w, self.n = ids, p, w, p.shape[1]
        safe = np.where(p > 0, p, 1.0)
        self.h = -(p * np.log2(safe)).sum(axis=1)
        self._noise: dict[tuple[int, int], np.ndarray] = {}

    def total(self) -> float:
        return float(self.w.sum())

    def mean(self) -> np.ndarray:
        return self.w.sum(axis=1) @ self.p / self.total()

    def hard(self, states: dict[int, tuple[Layout, np.ndarray]]) -> dict[int, Sums]:
        return {r: hard_block(self.p, self.w, layout, q) for r, (layout, q) in states.items()}

    def noise(self, seed: int, books: int) -> np.ndarray:
        if (seed, books) not in self._noise:
            self._noise[seed, books] = np.log2([[uniform(seed, int(i), NOISE_DRAW + b) for b in range(books)] for i in self.ids])
        return self._noise[seed, books]

    def soft(self, states: dict[int, tuple[Layout, int, np.ndarray, np.ndarray]]) -> dict[int, Sums]:
        return {r: soft_block(self.p, self.w, self.noise(seed, layout.books), layout, a, b) for r, (layout, seed, a, b) in states.items()}

    def rounded(self, states: dict[int, tuple[Layout, int, np.ndarray, np.ndarray]]) -> dict[int, Sums]:
        """Sums with each item given wholly to its likeliest book."""
        out = {}
        for r, (layout, seed, a, b) in states.items():
            out[r] = rounded_block(self.p, self.w, self.noise(seed, layout.books), layout, a, b)
        return out

    def draw(self, draws: list[Draw]) -> dict[int, np.ndarray]:
        out = {}
        for d in draws:
            weight = pool_weight(self.w, d.pool).copy()
            if len(d.books):
                weight = weight * np.maximum(cross(self.p, d.books).min(axis=1) - self.h, 0.0) ** d.power
            good = np.flatnonzero(weight > 0)
            if len(good):
                keys = np.array([-np.log(uniform(d.seed, int(self.ids[i]), d.draw)) for i in good]) / weight[good]
                out[d.run_id] = self.p[min(zip(keys, self.ids[good], good))[2]]
        return out


    def oversample(self, books: np.ndarray, seed: int, draw: int, expected: float, power: float) -> list[np.ndarray]:
        """Items kept with a chance by weight times a power of the divergence to ``books``; about ``expected`` of them."""
        weight = self.w.sum(axis=1) * np.maximum(cross(self.p, 0.999 * books + 0.001 * self.mean()).min(axis=1) - self.h, 0.0) ** power
        total = weight.sum()
        if not total > 0:
            return []
        return [self.p[i] for i in np.flatnonzero(weight > 0) if uniform(seed, int(self.ids[i]), draw) < expected * weight[i] / total]


def rounded_block(p: np.ndarray, w: np.ndarray, noise: np.ndarray, layout: Layout, a: np.ndarray, b: np.ndarray) -> Sums:
    out = Sums(np.zeros(layout.books), np.zeros((layout.books, p.shape[1])), np.zeros(layout.books))
    for channel in range(3):
        use = np.flatnonzero(w[:, channel] > 0)
        if len(use) and layout.allowed(channel).any():
            best = soft_shares(p[use], noise[use], layout, a, b, channel).argmax(axis=1)
            share = np.zeros((len(use), layout.books))
            share[np.arange(len(use)), best] = w[use, channel]
            out.t += share.sum(axis=0)
            out.s += share.T @ p[use]
    return out


class SparkEngine:
    """items: item_id, p, and one or three weights w0, w1, w2; persisted by the caller if it is read often."""

    def __init__(self, items: DataFrame, n: int):
        self.n = n
        self.channels = [c for c in ("w0", "w1", "w2") if c in items.columns]
        h = entropy_unrolled(F.col("p"), n) if n <= WIDE else entropy_bits("p")
        self.items = items.select("item_id", "p", h.alias("h"), *self.channels)
        self._totals = None
        self._noised: dict[tuple, DataFrame] = {}

    def release(self) -> None:
        """Give back the tables that the engine keeps."""
        for kept in self._noised.values():
            kept.unpersist()
        self._noised.clear()

    def noised(self, seeds: list[int], books: int) -> DataFrame:
        """item_id, p, weights and noise, an array of ``books`` uniform numbers for each seed; hashed once and kept."""
        if (key := (tuple(seeds), books)) not in self._noised:
            drawn = F.array(*(F.array(*(hash_uniform(seed, F.col("item_id"), NOISE_DRAW + b) for b in range(books))) for seed in seeds))
            self._noised[key] = self.items.select("item_id", "p", *self.channels, F.flatten(drawn).alias("noise")).persist()
        return self._noised[key]

    def _sums(self) -> list[float]:
        if self._totals is None:
            total = sum((F.col(c) for c in self.channels[1:]), F.col(self.channels[0]))
            heads = list(self.items.agg(F.sum(total), *(F.sum(c) for c in self.channels)).first())
            sums = _vector_sums(self.items.select("p", total.alias("w")), F.col("w")).collect()
            mean = np.zeros(self.n)
            for row in sums:
                mean[row["n"]] = row["s"]
            self._totals = [heads[0], *mean.tolist(), *heads[1:]]
        return self._totals

    def total(self) -> float:
        return self._sums()[0]

    def mean(self) -> np.ndarray:
        return np.array(self._sums()[1 : 1 + self.n]) / self.total()

    def oversample(self, books: np.ndarray, seed: int, draw: int, expected: float, power: float) -> list[np.ndarray]:
        """As the local engine's; a filter by hashed chances, whose few rows reach the driver."""
        dot = lambda b: F.aggregate(F.zip_with("p", b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
        total = sum((F.col(c) for c in self.channels[1:]), F.col(self.channels[0]))
        table = F.broadcast(self.items.sparkSession.createDataFrame([(code_bits(0.999 * books + 0.001 * self.mean()).tolist(),)], "bits array<array<double>>"))
        gap = F.greatest(F.lit(0.0), F.array_min(F.transform("bits", dot)) - F.col("h"))
        weighed = self.items.crossJoin(table).select("item_id", "p", (total * F.pow(gap, F.lit(power))).alias("weight"))
        mass = weighed.agg(F.sum("weight")).first()[0]
        if not mass:
            return []
        kept = weighed.filter((F.col("weight") > 0) & (hash_uniform(seed, F.col("item_id"), draw) < expected * F.col("weight") / mass))
        return [np.array(r["p"]) for r in kept.orderBy("item_id").select("p").collect()]  # about ``expected`` rows

    def _books(self, states: dict[int, tuple[Layout, np.ndarray]]) -> DataFrame:
        """One row per run: code lengths and pools of its books; the only thing that is sent out for a pass."""
        rows = [(r, code_bits(q).tolist(), layout.pools.tolist()) for r, (layout, q) in states.items()]
        return F.broadcast(self.items.sparkSession.createDataFrame(rows, "run_id int, bits array<array<double>>, pools array<int>"))

    def costs(self, states: dict[int, tuple[Layout, np.ndarray]]) -> DataFrame:
        """Items times runs, with the best book of each channel as a struct (cost, book)."""
        most = max(layout.books for layout, _ in states.values())
        joined = self.items.crossJoin(self._books(states))
        # A name of its own for each cost: nothing is priced twice, and the code stays flat.
        priced = joined.select("*", *(F.when(F.size("pools") > b, cost_unrolled(F.col("p"), F.get("bits", F.lit(b)), self.n)).alias(f"cost{b}") for b in range(most)))
        best = []
        for c, _ in enumerate(self.channels):
            structs = [F.when(F.get("pools", F.lit(b)).isin(0, c), F.struct(F.col(f"cost{b}").alias("cost"), F.lit(b).alias("book"))) for b in range(most)]
            best.append((F.least(*structs) if most > 1 else structs[0]).alias(f"best{c}"))
        return priced.select("run_id", "item_id", "p", "h", *self.channels, *best)

    def hard(self, states: dict[int, tuple[Layout, np.ndarray]]) -> dict[int, Sums]:
        out = self._hard(states)
        for r, (layout, _) in states.items():
            for channel, weight in enumerate(self._sums()[1 + self.n :]):
                if weight and not layout.allowed(channel).any():
                    out[r].cost[0] = np.inf
        return out

    def _hard(self, states: dict[int, tuple[Layout, np.ndarray]]) -> dict[int, Sums]:
        most = max(layout.books for layout, _ in states.values())
        if most * self.n > UNROLLED:
            return self._blocks({r: (layout, q) for r, (layout, q) in states.items()}, lambda p, w, _, state: hard_block(p, w, *state))
        parts = F.array(*(F.struct(F.col(c).alias("w"), F.col(f"best{i}.cost").alias("cost"), F.col(f"best{i}.book").alias("book")) for i, c in enumerate(self.channels)))
        rows = self.costs(states).select("run_id", "p", F.explode(parts).alias("c")).filter("c.w > 0 and c.book is not null")
        heads = rows.groupBy("run_id", F.col("c.book").alias("book")).agg(F.sum("c.w").alias("t"), F.sum(F.col("c.w") * F.col("c.cost")).alias("cost"), F.array(*(F.sum(F.col("c.w") * F.col("p")[i]) for i in range(self.n))).alias("s"))
        return self._gathered(heads, {r: layout for r, (layout, _) in states.items()})

    def _gathered(self, sums: DataFrame, layouts: dict[int, Layout]) -> dict[int, Sums]:
        out = {r: Sums(np.zeros(x.books), np.zeros((x.books, self.n)), np.zeros(x.books)) for r, x in layouts.items()}
        for row in sums.collect():  # runs times books rows
            held = out[row["run_id"]]
            held.t[row["book"]], held.cost[row["book"]], held.s[row["book"]] = row["t"], row["cost"], row["s"]
        return out

    def _blocks(self, states: dict[int, tuple], kernel, source: DataFrame | None = None) -> dict[int, Sums]:
        """A pass by matrix products over Arrow blocks; each block gives one row per run and used book.

        The kernel gets p, weights, a further column of ``source`` as a matrix, and a run's state.
        """
        n, channels = self.n, self.channels
        rest = [c for c in (source.columns if source is not None else []) if c not in ("item_id", "p", *channels)]
        sent = self.items.sparkSession.sparkContext.broadcast(states)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if not batch.num_rows:
                    continue
                p = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, n)
                w = np.zeros((len(p), 3))
                for i in range(len(channels)):
                    w[:, i] = batch.column(2 + i).to_numpy(zero_copy_only=False)
                more = batch.column(batch.num_columns - 1).flatten().to_numpy(zero_copy_only=False).reshape(len(p), -1) if rest else None
                for r, state in sent.value.items():
                    sums = kernel(p, w, more, state)
                    used = np.flatnonzero(sums.t > 0)
                    s = pa.ListArray.from_arrays(pa.array(np.arange(len(used) + 1) * n, pa.int32()), pa.array(sums.s[used].ravel()))
                    yield pa.RecordBatch.from_arrays([pa.array([r] * len(used), pa.int32()), pa.array(used, pa.int32()), pa.array(sums.t[used]), pa.array(sums.cost[used]), s], names=["run_id", "book", "t", "cost", "s"])

        rows = (self.items if source is None else source).select("item_id", "p", *channels, *rest).mapInArrow(run, "run_id int, book int, t double, cost double, s array<double>")
        return self._merged(rows, {r: state[0] for r, state in states.items()})

    def _merged(self, rows: DataFrame, layouts: dict[int, Layout]) -> dict[int, Sums]:
        """Block sums added up: a row for each run, book and symbol; the symbol -1 carries weight and cost."""
        parts = F.concat(F.array(F.struct(F.lit(-1).alias("n"), F.col("t").alias("x"), F.col("cost").alias("y"))), F.transform("s", lambda x, i: F.struct(i.alias("n"), x.alias("x"), F.lit(0.0).alias("y"))))
        summed = rows.select("run_id", "book", F.explode(parts).alias("e")).groupBy("run_id", "book", "e.n").agg(F.sum("e.x").alias("x"), F.sum("e.y").alias("y"))
        out = {r: Sums(np.zeros(x.books), np.zeros((x.books, self.n)), np.zeros(x.books)) for r, x in layouts.items()}
        for row in summed.collect():  # runs times books times symbols rows
            held = out[row["run_id"]]
            if row["n"] < 0:
                held.t[row["book"]], held.cost[row["book"]] = row["x"], row["y"]
            else:
                held.s[row["book"], row["n"]] = row["x"]
        return out

    def _shared(self, states: dict[int, tuple[Layout, int, np.ndarray, np.ndarray]], block) -> dict[int, Sums]:
        seeds = sorted({state[1] for state in states.values()})
        books = max(state[0].books for state in states.values())
        place = {seed: k * books for k, seed in enumerate(seeds)}

        def kernel(p: np.ndarray, w: np.ndarray, noise: np.ndarray, state: tuple) -> Sums:
            layout, seed, a, b = state
            return block(p, w, np.log2(noise[:, place[seed] : place[seed] + layout.books]), layout, a, b)

        return self._blocks(states, kernel, self.noised(seeds, books))

    def soft(self, states: dict[int, tuple[Layout, int, np.ndarray, np.ndarray]]) -> dict[int, Sums]:
        return self._shared(states, soft_block)

    def rounded(self, states: dict[int, tuple[Layout, int, np.ndarray, np.ndarray]]) -> dict[int, Sums]:
        return self._shared(states, rounded_block)

    def draw(self, draws: list[Draw]) -> dict[int, np.ndarray]:
        rows = [(d.run_id, str(d.seed), d.draw, d.pool, d.power, code_bits(d.books).tolist() if len(d.books) else []) for d in draws]
        asked = F.broadcast(self.items.sparkSession.createDataFrame(rows, "run_id int, seed string, draw int, pool int, power double, bits array<array<double>>"))
        most = max(len(d.books) for d in draws)
        total = sum((F.col(c) for c in self.channels[1:]), F.col(self.channels[0]))
        empty = [c for c, x in zip(self.channels, self._sums()[1 + self.n :]) if not x]
        weight = total
        for c in self.channels[1:]:
            if c not in empty:
                weight = F.when(F.col("pool") == int(c[1]), F.col(c)).otherwise(weight)
        if most * self.n > UNROLLED or self.n > WIDE:
            dot = lambda bits: F.aggregate(F.zip_with("p", bits, lambda x, y: F.when(x > 0, x * y).otherwise(F.lit(0.0))), F.lit(0.0), lambda s, x: s + x)
            nearest = [F.array_min(F.transform("bits", dot))]
        else:
            nearest = [F.when(F.size("bits") > b, cost_unrolled(F.col("p"), F.get("bits", F.lit(b)), self.n)) for b in range(most)]
        if nearest:
            gap = F.greatest(F.lit(0.0), (F.least(*nearest) if len(nearest) > 1 else nearest[0]) - F.col("h"))
            weight = weight * F.when(F.size("bits") > 0, F.pow(gap, F.col("power"))).otherwise(1.0)
        keyed = self.items.crossJoin(asked).withColumn("weight", weight)
        drawn = keyed.select("run_id", "item_id", "p", "weight", (-F.ln(hash_uniform(F.col("seed"), F.col("item_id"), F.col("draw")))).alias("drawn"))
        won = drawn.filter("weight > 0").withColumn("key", F.col("drawn") / F.col("weight")).groupBy("run_id").agg(F.min_by("p", F.struct("key", "item_id")).alias("p"))
        return {r["run_id"]: np.array(r["p"]) for r in won.collect()}  # one row per run


def _vector_sums(rows: DataFrame, weight: Column) -> DataFrame:
    """(n, s): weighted sums of the coordinates of p."""
    return rows.select(weight.alias("w"), F.posexplode("p").alias("n", "x")).groupBy("n").agg(F.sum(F.col("w") * F.col("x")).alias("s"))

