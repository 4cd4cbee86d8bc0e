"""Two users: joint demand, channels, costs, and designs with common codebooks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from prefbook.operators.assign import channels as assigned
from prefbook.operators.refine import Design, Run
from prefbook.plans.engine import Layout, SparkEngine
from prefbook.plans.planner import solve, sweep
from prefbook.schemas import ITEM_LENGTH


def cohort_log(requests: DataFrame, item: str = "item_id") -> DataFrame:
    """Requests with the cohort (odd or even user) that stands for one of two users."""
    return requests.select("event_id", (F.col("user_id") % 2).cast("int").alias("cohort"), F.col(item).alias("item"), "ts")


def joint_by_bucket(log: DataFrame, bucket: Column) -> DataFrame:
    """(i, j, f) from all pairs of requests of the two cohorts in one time bucket.

    Counts per bucket and item meet rather than requests: the join's rows are pairs of different items.
    """
    counts = log.groupBy("cohort", bucket.alias("bucket"), "item").agg(F.count("*").cast("double").alias("c"))
    left = counts.filter("cohort = 0").select("bucket", F.col("item").alias("i"), F.col("c").alias("c0"))
    right = counts.filter("cohort = 1").select("bucket", F.col("item").alias("j"), F.col("c").alias("c1"))
    return _shares(left.join(right, "bucket").groupBy("i", "j").agg(F.sum(F.col("c0") * F.col("c1")).alias("c")))


def joint_by_interval(log: DataFrame, minutes: int) -> DataFrame:
    """(i, j, f) from pairs of requests at most so many minutes apart; each looks into its own bucket and its neighbours."""
    width = 60 * minutes
    timed = log.withColumn("s", F.unix_timestamp(F.col("ts").cast("timestamp"))).withColumn("bucket", F.floor(F.col("s") / width))
    left = timed.filter("cohort = 0").select(F.col("item").alias("i"), F.col("s").alias("s0"), F.explode(F.array(*(F.col("bucket") + d for d in (-1, 0, 1)))).alias("bucket"))
    right = timed.filter("cohort = 1").select(F.col("item").alias("j"), F.col("s").alias("s1"), "bucket")
    near = left.join(right, "bucket").filter(F.abs(F.col("s0") - F.col("s1")) <= width)
    return _shares(near.groupBy("i", "j").agg(F.count("*").cast("double").alias("c")))


def joint_as_of(log: DataFrame, bucket: str = "hour") -> DataFrame:
    """(i, j, f) from each request with the other cohort's last one before it: linear in the requests.

    Requests are walked within buckets of time; what was last before a bucket comes from one row per bucket and cohort,
    so no task holds the whole log.
    """
    timed = log.withColumn("bucket", F.date_trunc(bucket, "ts"))
    within = Window.partitionBy("bucket").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    own = lambda c: F.when(F.col("cohort") == c, F.col("item"))
    walked = timed.select("bucket", "cohort", "item", *(F.last(own(c), ignorenulls=True).over(within).alias(f"l{c}") for c in (0, 1)))
    ends = timed.groupBy("bucket").agg(*(F.max_by(own(c), F.when(F.col("cohort") == c, F.struct("ts", "event_id"))).alias(f"e{c}") for c in (0, 1)))
    before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select("bucket", *(F.last(f"e{c}", ignorenulls=True).over(before).alias(f"b{c}") for c in (0, 1)))
    both = walked.join(carried, "bucket").select("cohort", "item", *(F.coalesce(f"l{c}", f"b{c}").alias(f"l{c}") for c in (0, 1)))
    i = F.when(F.col("cohort") == 0, F.col("item")).otherwise(F.col("l0"))
    j = F.when(F.col("cohort") == 1, F.col("item")).otherwise(F.col("l1"))
    pairs = both.select(i.alias("i"), j.alias("j")).filter("i is not null and j is not null")
    return _shares(pairs.groupBy("i", "j").agg(F.count("*").cast("double").alias("c")))


def _shares(counts: DataFrame) -> DataFrame:
    total = counts.agg(F.sum("c").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select("i", "j", (F.col("c") / F.col("total")).alias("f"))


def trace(joint: DataFrame) -> DataFrame:
    return joint.agg(F.coalesce(F.sum(F.when(F.col("i") == F.col("j"), F.col("f"))), F.lit(0.0)).alias("trace"))


def channels(joint: DataFrame) -> DataFrame:
    """(item_id, w0, w1, w2): both ask for the item, user 1 alone, user 2 alone."""
    off = F.when(F.col("i") != F.col("j"), F.col("f")).otherwise(F.lit(0.0))
    rows = joint.groupBy(F.col("i").alias("item_id")).agg(F.sum(F.col("f") - off).alias("w0"), F.sum(off).alias("w1"))
    columns = joint.groupBy(F.col("j").alias("item_id")).agg(F.sum(off).alias("w2"))
    return rows.join(columns, "item_id", "full").select("item_id", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in ("w0", "w1", "w2")))


def channels_by_bucket(log: DataFrame, bucket: Column) -> DataFrame:
    """The channels of ``joint_by_bucket`` without its pairs, linear in the requests.

    An item's share of all pairs is its count times the other cohort's total in each bucket; those with itself are
    the product of its two counts.
    """
    counts = log.groupBy(bucket.alias("bucket"), "item").agg(*(F.count_if(F.col("cohort") == c).cast("double").alias(f"c{c}") for c in (0, 1)))
    totals = counts.groupBy("bucket").agg(F.sum("c0").alias("t0"), F.sum("c1").alias("t1"))
    both = counts.join(totals, "bucket").groupBy(F.col("item").alias("item_id")).agg(
        F.sum(F.col("c0") * F.col("c1")).alias("same"), F.sum(F.col("c0") * F.col("t1")).alias("row"), F.sum(F.col("c1") * F.col("t0")).alias("column")
    )
    return _as_channels(both)


def channels_by_interval(log: DataFrame, minutes: int) -> DataFrame:
    """The channels of ``joint_by_interval`` without its pairs.

    The other cohort's requests around one are counted by a frame of time within buckets; each request stands in its own
    bucket as one that asks, and in that and its neighbours as one that is counted. Those for the same item are counted
    by a frame within item and bucket.
    """
    width = 60 * minutes
    timed = log.select("cohort", "item", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("s")).withColumn("own", F.floor(F.col("s") / width))
    spread = timed.withColumn("bucket", F.explode(F.array(*(F.col("own") + d for d in (-1, 0, 1)))))
    near = lambda *by: Window.partitionBy(*by, "bucket").orderBy("s").rangeBetween(-width, width)
    other = lambda w: F.when(F.col("cohort") == 0, F.count_if(F.col("cohort") == 1).over(w)).otherwise(F.count_if(F.col("cohort") == 0).over(w)).cast("double")
    counted = spread.withColumns({"around": other(near()), "same": other(near("item"))}).filter("bucket = own")
    sums = counted.groupBy(F.col("item").alias("item_id")).agg(
        F.sum(F.when(F.col("cohort") == 0, F.col("same"))).alias("same"), *(F.sum(F.when(F.col("cohort") == c, F.col("around"))).alias(name) for c, name in ((0, "row"), (1, "column")))
    )
    return _as_channels(sums.fillna(0.0, ["same", "row", "column"]))


def _as_channels(sums: DataFrame) -> DataFrame:
    """(item_id, w0, w1, w2) of the items that occur in a pair, from counts of pairs."""
    total = sums.agg(F.sum("row").alias("total"))
    part = lambda c: F.col(c) / F.col("total")
    rows = sums.filter("row > 0 or column > 0").crossJoin(F.broadcast(total))
    return rows.select("item_id", part("same").alias("w0"), ((F.col("row") - F.col("same")) / F.col("total")).alias("w1"), ((F.col("column") - F.col("same")) / F.col("total")).alias("w2"))


def even_channels(items: DataFrame, alpha: float) -> DataFrame:
    """Channels of the two-level matrix with trace alpha, in closed form: no matrix is built."""
    count = items.agg(F.count("*").alias("j"))
    return items.crossJoin(F.broadcast(count)).select("item_id", "p", (alpha / F.col("j")).alias("w0"), ((1 - alpha) / F.col("j")).alias("w1"), ((1 - alpha) / F.col("j")).alias("w2"))


def expected_bits(items: DataFrame, n: int, layout: Layout, q: np.ndarray, length: int = ITEM_LENGTH) -> DataFrame:
    """bits_per_request of both users together; an equal request is paid once."""
    return assigned(items, n, layout, q).agg((length * F.sum(F.col("w") * F.col("cost"))).alias("bits_per_request"))


def region_cost(items: DataFrame, n: int, layout: Layout, q: np.ndarray) -> DataFrame:
    """(channel, pool, book, w, cost): the mismatch cost as a sum over regions."""
    rows = assigned(items, n, layout, q).filter("w > 0")
    return rows.groupBy("channel", "pool", "book").agg(F.sum("w").alias("w"), F.sum(F.col("w") * (F.col("cost") - F.col("h"))).alias("cost"))


def update(items: DataFrame, n: int, layout: Layout, q: np.ndarray) -> DataFrame:
    """(pool, book, q): every book the mean of its regions in the channels that may use it."""
    rows = assigned(items, n, layout, q).filter("w > 0")
    sums = rows.groupBy("pool", "book").agg(*(F.sum(F.col("w") * F.col("p")[i]).alias(f"s{i}") for i in range(n)))
    mass = sum((F.col(f"s{i}") for i in range(1, n)), F.col("s0"))
    return sums.select("pool", "book", F.array(*(F.col(f"s{i}") / mass for i in range(n))).alias("q"))


def soft_means(shares: DataFrame, n: int) -> DataFrame:
    """(pool, k, q) for given shares: rows of channel, pool, k, w, r and p."""
    sums = shares.groupBy("pool", "k").agg(*(F.sum(F.col("w") * F.col("r") * F.col("p")[i]).alias(f"s{i}") for i in range(n)))
    mass = sum((F.col(f"s{i}") for i in range(1, n)), F.col("s0"))
    return sums.select("pool", "k", F.array(*(F.col(f"s{i}") / mass for i in range(n))).alias("q"))


def layouts(k1t: int, k2t: int, zero: bool = False) -> list[Layout]:
    """One layout for each number of common books; none are common only where asked for, and that serves no common request."""
    return [Layout(k0, k1t - k0, k2t - k0) for k0 in range(0 if zero else 1, min(k1t, k2t) + 1)]


def design(items: DataFrame, n: int, k1t: int, k2t: int, method: str = "refine", restarts: int = 2, zero: bool = False, **options) -> list[Design]:
    """The best design for each number of common books; all numbers and restarts are runs of one sweep."""
    runs = [Run(i * restarts + r, layout, seed=r + 1) for i, layout in enumerate(layouts(k1t, k2t, zero)) for r in range(restarts)]
    return _best_by_k0(solve(items, n, runs, method, **options))


def _best_by_k0(designs: list[Design]) -> list[Design]:
    best: dict[int, Design] = {}
    for d in designs:
        k0 = d.run.layout.k0
        if k0 not in best or d.cost < best[k0].cost:
            best[k0] = d
    return [best[k] for k in sorted(best)]


def design_sweep(problems: dict, n: int, k1t: int, k2t: int, method: str = "refine", restarts: int = 2, zero: bool = False, **options) -> dict:
    """``design`` for several demands at once: all problems, numbers of common books and restarts are runs of one job."""
    runs = [Run(i * restarts + r, layout, seed=r + 1) for i, layout in enumerate(layouts(k1t, k2t, zero)) for r in range(restarts)]
    return {key: _best_by_k0(found) for key, found in sweep(problems, n, runs, method, **options).items()}


def select(designs: list[Design]) -> Design:
    """The cheapest number of common books; ties go to fewer."""
    return min(designs, key=lambda d: (d.cost, d.run.layout.k0))


def separate(items: DataFrame, n: int, k1: int, k2: int, restarts: int = 2, **options) -> tuple[Design, Design]:
    """A design for each user's own requests, every request paid for by itself."""
    out = []
    for c, k in (("w1", k1), ("w2", k2)):
        own = items.select("item_id", "p", (F.col("w0") + F.col(c)).alias("f")).filter("f > 0")
        out.append(min(solve(own, n, [Run(r, Layout(k), r + 1) for r in range(restarts)], **options), key=lambda d: d.cost))
    return out[0], out[1]


def engine(items: DataFrame, n: int) -> SparkEngine:
    return SparkEngine(items, n)
