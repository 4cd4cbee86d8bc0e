"""Designs: fixed numbers of steps with SQL of the same steps, and full runs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.functions.uniform import hash_uniform
from prefbook.operators import baselines, fielditer, measures, pair, refine, sampled, simplex, spv
from prefbook.operators.dcdescent import descend, objective
from prefbook.operators.refine import Design, Run
from prefbook.plans.engine import NOISE_DRAW, Layout, SparkEngine
from prefbook.plans.planner import as_problem, best_of, solve
from prefbook.queries.fragments import PLOGP, collapsed, density, lattice, pool_assign, pool_means, pool_refined, pool_seeds, pool_soft, pooled, pools, refined, requests, seeded, with_
from prefbook.queries.fragments import books as books_sql
from prefbook.queries.fragments import simplex as simplex_sql
from prefbook.queries.fragments import spv as spv_sql
from prefbook.queries.fragments import uniform as u_sql
from prefbook.queries.measures import even_points
from prefbook.queries.models import part_points
from prefbook.queries.registry import query, r6, rounded, small
from prefbook.sources.tables import FIXTURES, fixture_items, fixture_spv, load, requests as request_log

STEPS = 3


def book_table(spark: SparkSession, q: np.ndarray, cost: float | None = None) -> DataFrame:
    rows = [(k, n, round(float(x), 6)) for k, row in enumerate(q) for n, x in enumerate(row)]
    out = small(spark, rows, "k int, n int, q double")
    return out if cost is None else out.withColumn("cost", F.lit(round(float(cost), 6)))


def summary(spark: SparkSession, designs: list[Design], name: str, length: int = 20) -> DataFrame:
    """One row per design: its layout, bits, whether all books are used, Kraft sums and a trace that never rises."""
    rows = []
    for d in designs:
        values = [x[1] for x in d.trace]
        falls = all(b <= a + 1e-9 for a, b in zip(values, values[1:]))
        lay = d.run.layout
        rows.append((name, d.run.run_id, lay.k0, lay.k1, lay.k2, round(length * d.cost, 6), len(values), falls, round(float(d.q.sum(axis=1).max()), 9), bool(d.used is None or d.used.all())))
    return small(spark, rows, "method string, run_id int, k0 int, k1 int, k2 int, bits_per_request double, steps int, monotone boolean, kraft_sum double, all_used boolean")


_BOOKS = "SELECT k::INT AS k, n::INT AS n, round(q, 6) AS q, (SELECT round(sum(f * c), 6) FROM b{t} JOIN tent USING (item_id)) AS cost FROM r{t}"


def _fixed_refine(spark: SparkSession, items: DataFrame, n: int, k: int, seed: int = 1) -> DataFrame:
    """Seeds and a fixed number of updates, by passes over the table."""
    d = solve(items, n, [Run(0, Layout(k), seed)], "refine", "passes by expressions", iterations=STEPS, fixed=True)[0]
    return book_table(spark, d.q, d.cost)


def _refined_sql(*source: str, k: int) -> str:
    return with_(*source, collapsed(), *seeded(k, 1, 2), *refined(f"s{k - 1}", STEPS)) + _BOOKS.format(t=STEPS)


@query(with_(spv_sql("events"), collapsed(), *seeded(3, 1, 2)) + "SELECT k::INT AS k, n::INT AS n, round(q, 6) AS q FROM s2")
def seed_plusplus(spark: SparkSession, sf_dir: str) -> DataFrame:
    types = spv.collapse_types(as_problem(fixture_items(spark, sf_dir, "events")))
    return book_table(spark, refine.seed_books(SparkEngine(types, 5), [Run(0, Layout(3), 1)])[0])


@query(_refined_sql(spv_sql("events"), k=3))
def refine_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fixed_refine(spark, fixture_items(spark, sf_dir, "events"), 5, 3)


@query(_refined_sql(spv_sql("parts"), k=3))
def refine_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fixed_refine(spark, fixture_items(spark, sf_dir, "parts"), 3, 3)


@query(_refined_sql(lattice(12), density("uniform", 3), k=2))
def field_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fixed_refine(spark, fielditer.nodes(spark, 3, 12, "uniform"), 3, 2)


@query(_refined_sql(lattice(12), density("distance", 3), k=2))
def field_nonuniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fixed_refine(spark, fielditer.nodes(spark, 3, 12, "distance"), 3, 2)


@query(_refined_sql(simplex_sql(3, 11, "SELECT i AS item_id FROM range(1000) r(i)"), k=2))
def sampled_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fixed_refine(spark, sampled.draw(spark, "uniform", 3, 1000), 3, 2)


_DRAWN = f"""cand_ids AS (SELECT i AS item_id FROM range(8000) r(i)),
cand_raw AS (SELECT item_id, n, -ln({u_sql("'11'", "item_id", "n")}) AS e FROM cand_ids, range(3) r(n)),
cand_spv AS (SELECT item_id, n, e / sum(e) OVER (PARTITION BY item_id) AS p FROM cand_raw),
kept AS (SELECT item_id FROM (SELECT item_id, sqrt(sum(pow(p - 1.0 / 3, 2))) AS d FROM cand_spv GROUP BY item_id) WHERE {u_sql("'11'", "item_id", "999")} * sqrt(1 - 1.0 / 3) <= d ORDER BY item_id LIMIT 1000),
spv AS (SELECT c.* FROM cand_spv c JOIN kept USING (item_id)), dem AS (SELECT item_id, 1.0 / 1000 AS f FROM kept)"""


def _spread_sql(n: int, count: int) -> str:
    steps = ", ".join(f"({i}, {a!r}::DOUBLE)" for i, a in enumerate(simplex.spread_steps(n)))
    return f"""steps(n, a) AS (VALUES {steps}), ids AS (SELECT i AS item_id FROM range({count}) r(i)),
raw AS (SELECT item_id, n, -ln(0.5 + item_id * a - floor(0.5 + item_id * a)) AS e FROM ids, steps),
spv AS (SELECT item_id, n, e / sum(e) OVER (PARTITION BY item_id) AS p FROM raw)"""


@query(
    with_(
        spv_sql("quarters"),
        _spread_sql(4, 400).replace("spv AS", "node AS"),
        f"near AS (SELECT item_id, arg_min(k, [c, k]) AS k FROM (SELECT s.item_id, m.item_id AS k, sum(-s.p * log2(m.p)) AS c FROM spv s JOIN node m USING (n) GROUP BY 1, 2) GROUP BY item_id)",
        "mass AS (SELECT k AS item_id, sum(f) AS f FROM near JOIN dem USING (item_id) GROUP BY k)",
    )
    + "SELECT item_id, n::INT AS n, round(p, 6) AS p, round(coalesce(f, 0), 6) AS f FROM node LEFT JOIN mass USING (item_id)"
)
def field_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Low-discrepancy nodes over four symbols, with the demand of the customers near each as their density."""
    nodes = fielditer.nodes(spark, 4, 20, "uniform")
    rows = spv.exploded(fielditer.filled(fixture_items(spark, sf_dir, "quarters"), nodes))
    return rounded(rows.withColumn("n", F.col("n").cast("int")), "p", "f").select("item_id", "n", "p", "f")


@query(_refined_sql(simplex_sql(3, 11, "SELECT i AS item_id FROM range(1000) r(i)").split(",\ndem AS")[0], density("distance", 3), k=2))
def sampled_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A uniform sample with the density as weight, in place of rejection."""
    return _fixed_refine(spark, sampled.draw(spark, "distance", 3, 1000, how="weight"), 3, 2)


@query(_refined_sql(_DRAWN, k=2))
def sampled_nonuniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fixed_refine(spark, sampled.draw(spark, "distance", 3, 1000), 3, 2)


def _soft_sql(books: int, outer: int, inner: int) -> list[str]:
    """x0, x1, ...: log shares of types in books after each inner step; t and s: their sums."""
    sums = lambda i: [
        f"p{i} AS (SELECT item_id, k, pow(2, x - max(x) OVER (PARTITION BY item_id)) AS r FROM x{i})",
        f"q{i} AS (SELECT item_id, k, r / sum(r) OVER (PARTITION BY item_id) AS r FROM p{i})",
        f"t{i} AS (SELECT k, sum(f * r) AS t FROM q{i} JOIN tent USING (item_id) GROUP BY k)",
        f"y{i} AS (SELECT k, n, sum(f * r * p) AS s FROM q{i} JOIN tspv USING (item_id) GROUP BY k, n)",
    ]
    out = [f"x0 AS (SELECT item_id, k, log2({u_sql(chr(39) + '1' + chr(39), 'item_id', f'(k + {NOISE_DRAW})')}) AS x FROM tent, range({books}) b(k))", *sums(0)]
    step = 0
    for _ in range(outer):
        tangent = step
        for _ in range(inner):
            out.append(f"x{step + 1} AS (SELECT x.item_id, x.k, x.x + g.g - log2(t.t) AS x FROM x{step} x JOIN t{step} t USING (k) JOIN (SELECT item_id, k, sum(p * log2(s)) AS g FROM tspv JOIN y{tangent} USING (n) GROUP BY item_id, k) g ON g.item_id = x.item_id AND g.k = x.k)")
            step += 1
            out += sums(step)
    return out


def _soft_objective(i: int) -> str:
    return f"(SELECT sum(t * log2(t)) FROM t{i}) - (SELECT sum(s * log2(s)) FROM y{i})"


@query(with_(spv_sql("events"), collapsed(), *_soft_sql(3, 0, 0)) + f"SELECT round({_soft_objective(0)}, 6) AS objective")
def soft_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    types = spv.collapse_types(as_problem(fixture_items(spark, sf_dir, "events")))
    sums = SparkEngine(types, 5).soft({0: (Layout(3), 1, np.zeros(3), np.zeros((3, 5)))})[0]
    return small(spark, [(round(objective(sums), 6),)], "objective double")


@query(with_(spv_sql("events"), collapsed(), *_soft_sql(3, 2, 2)) + f"SELECT i::INT AS step, round(o, 6) AS objective FROM (SELECT 0 AS i, {_soft_objective(0)} AS o UNION ALL SELECT 1, {_soft_objective(2)} UNION ALL SELECT 2, {_soft_objective(4)})")
def dc_fixed_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    types = spv.collapse_types(as_problem(fixture_items(spark, sf_dir, "events")))
    d = descend(SparkEngine(types, 5), [Run(0, Layout(3), 1)], inner=2, outer=2, fixed=True)[0]
    return small(spark, [(i, round(v, 6)) for i, v, _ in d.trace], "step int, objective double")


def _dc(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    n = len(FIXTURES[name].alphabet)
    items = fixture_items(spark, sf_dir, name)
    runs = [Run(r, Layout(3), r + 1) for r in range(2)]
    both = [summary(spark, solve(items, n, runs, "dc", rounding=how), f"dc {how}") for how in ("argmax", "nearest")]
    return both[0].unionByName(both[1])


@query()
def dc_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _dc(spark, sf_dir, "events")


@query()
def dc_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _dc(spark, sf_dir, "parts")


@query()
def refine_restarts(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = [Run(10 * k + r, Layout(k), r + 1) for k in (1, 2, 4, 8) for r in range(3)]
    return summary(spark, solve(fixture_items(spark, sf_dir, "events"), 5, runs), "refine")


@query()
def refine_parallel_seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Oversampled seeding: passes don't grow with the number of books."""
    runs = [Run(r, Layout(6), r + 1) for r in range(3)]
    return summary(spark, solve(even_points(spark, sf_dir, 4), 4, runs, seeding="parallel"), "refine, parallel seeds")


@query()
def block_skipping(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks, decided blocks, items that an update still reads, and whether it gives the sums of a whole pass."""
    from prefbook.plans import blocks

    q = simplex.portable_books(3, 3)
    blocked = blocks.with_blocks(fixture_items(spark, sf_dir, "parts"), 3).persist()
    stats = blocks.decided(blocks.statistics(blocked, 3), q).persist()
    read = blocked.join(stats.filter("k is null").select("block"), "block", "left_semi").count()
    own = {r["k"]: r for r in blocks.update(blocked, stats.drop("k"), q).collect()}
    whole = SparkEngine(as_problem(blocked), 3).hard({0: (Layout(3), q)})[0]
    same = all(abs(own[k]["w"] - whole.t[k]) < 1e-9 for k in own)
    row = (stats.count(), stats.filter("k is not null").count(), blocked.count(), read, same)
    blocked.unpersist()
    stats.unpersist()
    return small(spark, [row], "blocks long, decided long, items long, items_read long, same boolean")


@query()
def three_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three users with even channels: bits with common books, with books of pairs, and with books of their own only."""
    from prefbook.operators import multiuser
    from prefbook.plans.planner import local_engine

    engine = local_engine(spv.collapse_types(as_problem(even_points(spark, sf_dir, 3))), 3)
    count = len(multiuser.user_channels(3))
    w = np.repeat(engine.w[:, :1], count, axis=1) / count
    rows = []
    for name, sizes in (("common", (((1, 2, 3), 4),)), ("common and own", (((1, 2, 3), 2), ((1,), 2), ((2,), 2), ((3,), 2))), ("common and pairs", (((1, 2, 3), 2), ((1, 2), 1), ((1, 3), 1), ((2, 3), 1)))):
        best = min(multiuser.design(engine.p, w, multiuser.SharedLayout(3, sizes), seed)[1] for seed in range(1, 5))
        rows.append((name, sum(k for _, k in sizes), round(20 * best, 6)))
    return small(spark, rows, "layout string, books int, bits_per_request double")


@query()
def refine_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """64 symbols and 10 books: beyond straight-line code, so passes are matrix products over Arrow blocks."""
    vectors = spv.from_vector(load(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    even = vectors.crossJoin(F.broadcast(vectors.agg((1.0 / F.count("*")).alias("f"))))
    designs = solve(even, 64, [Run(0, Layout(10), 1)], "refine", "passes over blocks", iterations=8)
    return summary(spark, designs, "refine")


@query(f"SELECT (100 * m + r)::INT AS run_id, ({STEPS} + 1)::BIGINT AS steps, true AS monotone FROM range(2) a(m), range(3) b(r)")
def trace_monotone(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Neither method ever raises its objective, by the numbers of a fixed count of steps."""
    runs = [Run(r, Layout(3), r + 1) for r in range(3)]
    items = fixture_items(spark, sf_dir, "events")
    options = {"refine": {"iterations": STEPS, "mix": 0.02}, "dc": {"outer": STEPS}}
    rows = [(100 * m + d.run.run_id, i, float(v)) for m, method in enumerate(options) for d in solve(items, 5, runs, method, fixed=True, **options[method]) for i, v, _ in d.trace]
    return measures.monotone(small(spark, rows, "run_id int, iteration int, objective double"))


@query()
def gain_per_book(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = [Run(10 * k + r, Layout(k), r + 1) for k in range(1, 7) for r in range(3)]
    best: dict[int, float] = {}
    for d in solve(even_points(spark, sf_dir, 3), 3, runs):
        best[d.run.layout.k0] = min(best.get(d.run.layout.k0, float("inf")), 20 * d.cost)
    report = small(spark, [(3, k, round(v, 6)) for k, v in sorted(best.items())], "n int, k int, bits_per_request double")
    return measures.gain_per_book(report, ["n"])


@query()
def gap_to_exhaustive(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prefbook.operators import exhaustive

    points = fielditer.nodes(spark, 3, 24, "uniform")
    _, best = exhaustive.search(points, 16, 2)
    own = best_of(solve(points, 3, [Run(r, Layout(2), r + 1) for r in range(4)]))
    return small(spark, [("refine", round(20 * own.cost, 6), round(20 * best, 6), round(20 * (own.cost - best), 6))], "method string, bits_per_request double, exhaustive double, gap double")


# --- two users ---------------------------------------------------------------------------

_JOINT = """lg AS (SELECT event_id, (user_id % 2)::INT AS cohort, item_id AS item, date_trunc('hour', ts) AS bucket, ts FROM req),
jc AS (SELECT a.item AS i, b.item AS j, count(*)::DOUBLE AS c FROM lg a JOIN lg b ON a.bucket = b.bucket AND a.cohort = 0 AND b.cohort = 1 GROUP BY 1, 2),
joint AS (SELECT i, j, c / sum(c) OVER () AS f FROM jc)"""
_CHANNELS = """wr AS (SELECT i AS item_id, sum(CASE WHEN i = j THEN f ELSE 0 END) AS w0, sum(CASE WHEN i <> j THEN f ELSE 0 END) AS w1 FROM joint GROUP BY i),
wc AS (SELECT j AS item_id, sum(CASE WHEN i <> j THEN f ELSE 0 END) AS w2 FROM joint GROUP BY j),
ch AS (SELECT coalesce(wr.item_id, wc.item_id) AS item_id, coalesce(w0, 0) AS w0, coalesce(w1, 0) AS w1, coalesce(w2, 0) AS w2 FROM wr FULL JOIN wc ON wr.item_id = wc.item_id)"""


def joint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pair.joint_by_bucket(pair.cohort_log(request_log(spark, sf_dir)), F.date_trunc("hour", "ts"))


def pair_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    log = pair.cohort_log(request_log(spark, sf_dir))
    return pair.channels_by_bucket(log, F.date_trunc("hour", "ts")).join(fixture_spv(spark, sf_dir, "events"), "item_id").select("item_id", "p", "w0", "w1", "w2")


@query(with_(requests(), _JOINT) + "SELECT i, j, round(f, 6) AS f FROM joint")
def joint_hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(joint(spark, sf_dir), "f")


@query(
    with_(requests(), _JOINT, "near AS (SELECT a.item AS i, b.item AS j, count(*)::DOUBLE AS c FROM lg a JOIN lg b ON a.cohort = 0 AND b.cohort = 1 AND abs(floor(epoch(a.ts))::BIGINT - floor(epoch(b.ts))::BIGINT) <= 600 GROUP BY 1, 2)")
    + "SELECT i, j, round(c / sum(c) OVER (), 6) AS f FROM near"
)
def joint_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(pair.joint_by_interval(pair.cohort_log(request_log(spark, sf_dir)), 10), "f")


_ASOF = """walk AS (SELECT cohort, item, last_value(CASE WHEN cohort = 0 THEN item END IGNORE NULLS) OVER w AS l0, last_value(CASE WHEN cohort = 1 THEN item END IGNORE NULLS) OVER w AS l1
    FROM lg WINDOW w AS (ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
prs AS (SELECT CASE WHEN cohort = 0 THEN item ELSE l0 END AS i, CASE WHEN cohort = 1 THEN item ELSE l1 END AS j FROM walk)"""


@query(with_(requests(), _JOINT, _ASOF) + "SELECT i, j, round(count(*) / sum(count(*)) OVER (), 6) AS f FROM prs WHERE i IS NOT NULL AND j IS NOT NULL GROUP BY i, j")
def joint_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(pair.joint_as_of(pair.cohort_log(request_log(spark, sf_dir))), "f")


@query(with_(requests(), _JOINT) + "SELECT round(coalesce(sum(f) FILTER (WHERE i = j), 0), 6) AS trace FROM joint")
def joint_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(pair.trace(joint(spark, sf_dir)), "trace")


@query(with_(requests(), _JOINT, _CHANNELS) + "SELECT item_id, round(w0, 6) AS w0, round(w1, 6) AS w1, round(w2, 6) AS w2 FROM ch")
def pair_channels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(pair.channels_by_bucket(pair.cohort_log(request_log(spark, sf_dir)), F.date_trunc("hour", "ts")), "w0", "w1", "w2")


_NEAR = "near AS (SELECT a.item AS i, b.item AS j, count(*)::DOUBLE AS c FROM lg a JOIN lg b ON a.cohort = 0 AND b.cohort = 1 AND abs(floor(epoch(a.ts))::BIGINT - floor(epoch(b.ts))::BIGINT) <= 600 GROUP BY 1, 2)"


@query(with_(requests(), _JOINT.split(",\njc AS")[0], _NEAR, "joint AS (SELECT i, j, c / sum(c) OVER () AS f FROM near)", _CHANNELS) + "SELECT item_id, round(w0, 6) AS w0, round(w1, 6) AS w1, round(w2, 6) AS w2 FROM ch")
def pair_channels_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Channels of requests at most ten minutes apart, by frames of time in place of pairs."""
    return rounded(pair.channels_by_interval(pair.cohort_log(request_log(spark, sf_dir)), 10), "w0", "w1", "w2")


@query(with_(requests(), _JOINT, _CHANNELS) + "SELECT item_id, round(w0, 6) AS w0, round(w1, 6) AS w1, round(w2, 6) AS w2 FROM ch")
def pair_channels_of_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same channels from a joint demand that is given as a matrix."""
    return rounded(pair.channels(joint(spark, sf_dir)), "w0", "w1", "w2")


LAYOUT = Layout(2, 2, 1)
_POOLS = "pools AS (SELECT k, CASE WHEN k < 2 THEN 0 WHEN k < 4 THEN 1 ELSE 2 END AS pool FROM range(5) r(k))"
_ROWS = """chan AS (SELECT item_id, 0 AS channel, w0 AS w FROM ch UNION ALL SELECT item_id, 1, w1 FROM ch UNION ALL SELECT item_id, 2, w2 FROM ch),
pick AS (SELECT item_id, channel, w, k, pool, c FROM (
    SELECT chan.*, k, pool, c, row_number() OVER (PARTITION BY chan.item_id, channel ORDER BY c, k) AS rn FROM chan JOIN cost USING (item_id) JOIN pools USING (k) WHERE pool = 0 OR pool = channel) WHERE rn = 1)"""


def _pair_sql(*more: str) -> str:
    from prefbook.queries.fragments import costs, entropy

    return with_(spv_sql("events"), requests(), _JOINT, _CHANNELS, books_sql(5, 5), entropy(), costs(), _POOLS, _ROWS, *more)


@query(_pair_sql() + "SELECT round(20 * sum(w * c), 6) AS bits_per_request FROM pick")
def pair_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(pair.expected_bits(pair_items(spark, sf_dir), 5, LAYOUT, simplex.portable_books(5, 5)), "bits_per_request")


@query(_pair_sql() + "SELECT item_id, channel::INT AS channel, pool::INT AS pool, k::INT AS book FROM pick")
def pair_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prefbook.operators import assign

    rows = assign.channels(pair_items(spark, sf_dir), 5, LAYOUT, simplex.portable_books(5, 5))
    return rows.select("item_id", "channel", "pool", "book")


@query(_pair_sql() + "SELECT channel::INT AS channel, pool::INT AS pool, k::INT AS book, round(sum(w), 6) AS w, round(sum(w * (c - h)), 6) AS cost FROM pick JOIN ent USING (item_id) WHERE w > 0 GROUP BY 1, 2, 3")
def pair_region_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(pair.region_cost(pair_items(spark, sf_dir), 5, LAYOUT, simplex.portable_books(5, 5)), "w", "cost")


@query(_pair_sql() + "SELECT pool::INT AS pool, k::INT AS book, n::INT AS n, round(sum(w * p) / sum(sum(w * p)) OVER (PARTITION BY k), 6) AS q FROM pick JOIN spv USING (item_id) WHERE w > 0 GROUP BY pool, k, n")
def pair_update(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(spv.exploded(pair.update(pair_items(spark, sf_dir), 5, LAYOUT, simplex.portable_books(5, 5)), "q", "q"), "q")


_SHARES = f"raw_shares AS (SELECT item_id, channel, w, k, pool, {u_sql(chr(39) + '3' + chr(39), 'item_id', 'k')} AS u FROM chan, pools WHERE pool = 0 OR pool = channel), shr AS (SELECT *, u / sum(u) OVER (PARTITION BY item_id, channel) AS r FROM raw_shares)"


@query(_pair_sql(_SHARES) + "SELECT pool::INT AS pool, k::INT AS k, n::INT AS n, round(sum(w * r * p) / sum(sum(w * r * p)) OVER (PARTITION BY k), 6) AS q FROM shr JOIN spv USING (item_id) GROUP BY pool, k, n")
def pair_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import Window

    items = pair_items(spark, sf_dir)
    stacked = items.select("item_id", "p", F.posexplode(F.array("w0", "w1", "w2")).alias("channel", "w"))
    pools = F.broadcast(small(spark, [(k, int(pool)) for k, pool in enumerate(LAYOUT.pools)], "k int, pool int"))
    drawn = stacked.join(pools, (F.col("pool") == 0) | (F.col("pool") == F.col("channel"))).withColumn("u", hash_uniform(3, F.col("item_id"), F.col("k")))
    shares = drawn.withColumn("r", F.col("u") / F.sum("u").over(Window.partitionBy("item_id", "channel")))
    return rounded(spv.exploded(pair.soft_means(shares, 5), "q", "q"), "q")


_PAIR_TYPES = "dem2 AS (SELECT item_id, w0 + w1 + w2 AS f FROM ch)"


@query(with_(spv_sql("events"), requests(), _JOINT, _CHANNELS, _PAIR_TYPES, collapsed().replace("JOIN dem USING", "JOIN dem2 USING"), *seeded(3, 1, 2)) + "SELECT k::INT AS k, n::INT AS n, round(q, 6) AS q FROM s2")
def pair_seed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seeds of a common pool: by the chance that anyone asks for the item."""
    types = spv.collapse_types(pair_items(spark, sf_dir))
    return book_table(spark, refine.seed_books(SparkEngine(types, 5), [Run(0, Layout(3, 0, 0), 1)])[0])


def _pair_refined(steps: int) -> list[str]:
    out = ["r0 AS (SELECT * FROM s2)"]
    for t in range(steps + 1):
        out.append(f"c{t} AS (SELECT item_id, k, sum(CASE WHEN p > 0 THEN -p * log2(q) ELSE 0 END) AS c FROM spv JOIN r{t} USING (n) GROUP BY item_id, k)")
        out.append(f"b{t} AS (SELECT item_id, k, c, w0 + w1 + w2 AS w FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY c, k) AS rn FROM c{t}) JOIN ch USING (item_id) WHERE rn = 1)")
        if t < steps:
            out.append(f"r{t + 1} AS (SELECT k, n, sum(w * p) / sum(sum(w * p)) OVER (PARTITION BY k) AS q FROM spv JOIN b{t} USING (item_id) GROUP BY k, n)")
    return out


@query(
    with_(spv_sql("events"), requests(), _JOINT, _CHANNELS, _PAIR_TYPES, collapsed().replace("JOIN dem USING", "JOIN dem2 USING"), *seeded(3, 1, 2), *_pair_refined(STEPS))
    + f"SELECT k::INT AS k, n::INT AS n, round(q, 6) AS q, (SELECT round(sum(w * c), 6) FROM b{STEPS}) AS cost FROM r{STEPS}"
)
def pair_refine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All books common: seeds and a fixed number of updates over the three channels."""
    d = solve(pair_items(spark, sf_dir), 5, [Run(0, Layout(3, 0, 0), 1)], "refine", "passes by expressions", iterations=STEPS, fixed=True)[0]
    return book_table(spark, d.q, d.cost)


_POOLED = (2, 1, 1)


def _pool_sql(layout: tuple[int, int, int], *more: str) -> str:
    return with_(spv_sql("events"), requests(), _JOINT, _CHANNELS, *pooled(layout), *more)


@query(_pool_sql(_POOLED, *pool_seeds(_POOLED, 1)) + "SELECT k::INT AS k, n::INT AS n, round(q, 6) AS q FROM s3")
def pair_seed_pools(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seeds of a common and of two exclusive pools."""
    types = spv.collapse_types(pair_items(spark, sf_dir))
    return book_table(spark, refine.seed_books(SparkEngine(types, 5), [Run(0, Layout(*_POOLED), 1)])[0])


@query(_pool_sql(_POOLED, *pool_seeds(_POOLED, 1), *pool_refined("s3", STEPS)) + f"SELECT k::INT AS k, n::INT AS n, round(q, 6) AS q, (SELECT round(sum(w * c), 6) FROM b{STEPS}) AS cost FROM r{STEPS}")
def pair_refine_pools(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Common and exclusive books: seeds and a fixed number of updates over the three channels."""
    d = solve(pair_items(spark, sf_dir), 5, [Run(0, Layout(*_POOLED), 1)], "refine", "passes by expressions", iterations=STEPS, fixed=True)[0]
    return book_table(spark, d.q, d.cost)


_CURVE = {k0: (k0, 3 - k0, 3 - k0) for k0 in (1, 2, 3)}


def _curve_sql() -> str:
    parts = [x for k0, layout in _CURVE.items() for x in (pools(layout, f"pools{k0}"), *pool_seeds(layout, 1, f"z{k0}"), *pool_refined(f"z{k0}s{sum(layout) - 1}", STEPS, f"z{k0}", f"pools{k0}"))]
    costs = " UNION ALL ".join(f"SELECT {k0} AS k0, (SELECT 20 * sum(w * c) FROM z{k0}b{STEPS}) AS bits" for k0 in _CURVE)
    return _pool_sql(_POOLED, *parts) + f"SELECT k0::INT AS k0, round(bits, 6) AS bits_per_request, k0 = arg_min(k0, bits) OVER () AS best FROM ({costs})"


@query(_curve_sql())
def pair_k0_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cost by the number of common books after a fixed number of updates, and the cheapest."""
    runs = [Run(k0, Layout(*layout), 1) for k0, layout in _CURVE.items()]
    designs = solve(pair_items(spark, sf_dir), 5, runs, "refine", iterations=STEPS, fixed=True)
    best = pair.select(designs).run.layout.k0
    return small(spark, [(d.run.layout.k0, round(20 * d.cost, 6), d.run.layout.k0 == best) for d in designs], "k0 int, bits_per_request double, best boolean")


_DC_STEPS = (2, 2)
_DC_LAST = _DC_STEPS[0] * _DC_STEPS[1]


def _pair_dc_sql() -> str:
    soft = f"soft AS (SELECT k, n, s / sum(s) OVER (PARTITION BY k) AS q FROM y{_DC_LAST})"
    likeliest = f"likely AS (SELECT item_id, channel, w, k FROM (SELECT *, row_number() OVER (PARTITION BY item_id, channel ORDER BY r DESC, k) AS rn FROM q{_DC_LAST}) WHERE rn = 1)"
    parts = [
        *pool_soft(3, 1, *_DC_STEPS, NOISE_DRAW), soft, likeliest, pool_means("likely", "soft", "ab"), *pool_assign("ab", "fa"),
        *pool_assign("soft", "near0"), pool_means("near0", "soft", "nb"), *pool_assign("nb", "fn"),
    ]
    objective = f"round((SELECT sum(t * log2(t)) FROM t{_DC_LAST}) - (SELECT sum(s * log2(s)) FROM y{_DC_LAST} WHERE s > 0), 6)"
    rows = " UNION ALL ".join(f"SELECT '{how}' AS rounding, {objective} AS objective, round((SELECT sum(w * c) FROM {into}), 6) AS cost" for how, into in (("argmax", "fa"), ("nearest", "fn")))
    return _pool_sql((1, 1, 1), *parts) + rows


@query(_pair_dc_sql())
def pair_dc_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Soft shares of common and exclusive books after a fixed number of steps, and the cost by both roundings."""
    outer, inner = _DC_STEPS
    types = spv.collapse_types(pair_items(spark, sf_dir)).persist()
    rows = []
    for how in ("argmax", "nearest"):
        engine = SparkEngine(types, 5)
        d = descend(engine, [Run(0, Layout(1, 1, 1), 1)], inner=inner, outer=outer, rounding=how, fixed=True)[0]
        engine.release()
        rows.append((how, round(d.trace[-1][1], 6), round(d.cost, 6)))
    types.unpersist()
    return small(spark, rows, "rounding string, objective double, cost double")


@query()
def pair_refine_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    return summary(spark, pair.design(pair_items(spark, sf_dir), 5, 3, 3, "refine"), "refine")


@query()
def pair_dc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both roundings of the soft shares, by the number of common books."""
    items = pair_items(spark, sf_dir)
    both = [summary(spark, pair.design(items, 5, 3, 3, "dc", rounding=how), f"dc {how}") for how in ("argmax", "nearest")]
    return both[0].unionByName(both[1])


@query()
def pair_k0_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cost by the number of common books, and the cheapest, for common and for mostly lone requests."""
    rows = []
    points = part_points(spark, sf_dir, 3, 42)
    for alpha, designs in pair.design_sweep({a: pair.even_channels(points, a) for a in (0.05, 0.75)}, 3, 4, 4).items():
        best = pair.select(designs).run.layout.k0
        rows += [(alpha, d.run.layout.k0, round(20 * d.cost, 6), d.run.layout.k0 == best) for d in designs]
    return small(spark, rows, "alpha double, k0 int, bits_per_request double, best boolean")


@query()
def pair_separate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Without a common request, no common books: the design with none is two designs of their own."""
    items = pair_items(spark, sf_dir).withColumn("w0", F.lit(0.0))
    joint_design = [d for d in pair.design(items, 5, 2, 2, zero=True, restarts=3) if d.run.layout.k0 == 0][0]
    one, two = pair.separate(items, 5, 2, 2, restarts=3)
    return small(spark, [("together", round(20 * joint_design.cost, 6)), ("apart", round(20 * (one.cost + two.cost), 6))], "design string, bits_per_request double")


@query()
def separate_unicast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two designs of their own, every request paid for by itself, beside one with common books."""
    items = pair.even_channels(part_points(spark, sf_dir, 3, 42), 0.5)
    one, two = pair.separate(items, 3, 4, 4)
    shared = pair.select(pair.design(items, 3, 4, 4))
    return small(spark, [("separate", round(20 * (one.cost + two.cost), 6)), ("shared", round(20 * shared.cost, 6))], "design string, bits_per_request double")


def self_decodable_by_alpha(points: DataFrame, n: int, support_only: bool = False) -> DataFrame:
    """(alpha, bits_per_request) of two users who ask for all points evenly."""
    out = None
    for alpha in (0.0, 0.25, 0.5, 0.75, 1.0):
        row = baselines.self_decodable_pair(pair.even_channels(points, alpha), n, support_only=support_only).select(F.lit(alpha).alias("alpha"), r6("bits_per_request").alias("bits_per_request"))
        out = row if out is None else out.unionByName(row)
    return out


@query(
    with_(spv_sql("customers"), f"own AS (SELECT item_id, sum(20 * ({PLOGP}) + CASE WHEN p > 0 THEN -log2(p) ELSE 0 END) AS b FROM spv GROUP BY item_id)")
    + "SELECT a.alpha::DOUBLE AS alpha, round((2 - a.alpha) * avg(b), 6) AS bits_per_request FROM own, (VALUES (0.0), (0.25), (0.5), (0.75), (1.0)) a(alpha) GROUP BY a.alpha"
)
def self_decodable_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both users ask for customers evenly, by the share of common requests; a book travels with the symbols that its item has."""
    return self_decodable_by_alpha(fixture_spv(spark, sf_dir, "customers"), 5, support_only=True)


@query()
def mismatched_demand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Books designed for one demand, priced under another, beside books designed for it."""
    items = fixture_items(spark, sf_dir, "parts")
    squared = items.agg(F.sum(F.col("p")[0] * F.col("f")).alias("m"))
    items = items.crossJoin(F.broadcast(squared)).withColumn("g", F.col("f") * F.col("p")[0] / F.col("m")).drop("m")
    runs = [Run(r, Layout(2), r + 1) for r in range(3)]
    rows = []
    for name, weight in (("for f", "f"), ("for g", "g")):
        books = best_of(solve(items.select("item_id", "p", F.col(weight).alias("f")), 3, runs)).q
        rows.append((name, round(baselines.mismatched_demand(items, books, "g").first()[0], 6)))
    return small(spark, rows, "books string, bits_under_g double")


