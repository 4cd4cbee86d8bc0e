"""The experiments on the given tables, as design reports."""

from __future__ import annotations



import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.operators import baselines, exhaustive, fielditer, measures, pair, sampled, simplex, single
from prefbook.operators.refine import Design, Run
from prefbook.plans.engine import Layout, cross
from prefbook.plans.planner import best_of, local_engine, solve
from prefbook.operators.spv import collapse_types
from prefbook.queries.designs import _CHANNELS, pair_items
from prefbook.queries.fragments import PLOGP, priced, simplex as simplex_sql, with_
from prefbook.queries.measures import even_points
from prefbook.queries.models import _PART_IDS, part_points
from prefbook.queries.registry import query, rounded, small
from prefbook.queries.relational import DEMO
from prefbook.schemas import DESIGN_REPORT, ITEM_LENGTH
from prefbook.sources.tables import fixture_items, fixture_spv, load, requests as request_log


def report(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """Rows (method, n, k, k0, bits, floor, baseline) as a design report."""
    out = [(m, n, k, k0, round(b, 6), round((b - floor) / ITEM_LENGTH, 6), round(floor, 6), round(100 * (1 - b / base), 6) if base and np.isfinite(base) else None) for m, n, k, k0, b, floor, base in rows]
    return small(spark, out, DESIGN_REPORT)


def value(df: DataFrame) -> float:
    return float(df.first()[0])


@query(
    "SELECT * FROM (VALUES ('edge codebook, first two items', 1.0::DOUBLE), ('preference-blind codebook', 2.0::DOUBLE), ('divergence of the first item', 0.188722::DOUBLE)) t(measure, bits_per_symbol)"
)
def w0_demo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four items over four symbols: a user of the first two never sees the last two symbols."""
    items = small(spark, [(i, p, 0.5 if i < 3 else 0.0) for i, p in DEMO], "item_id long, p array<double>, f double")
    edge = single.book(items, 4)
    rows = [
        ("edge codebook, first two items", round(value(measures.expected_bits(items, edge, 1)), 6)),
        ("preference-blind codebook", round(value(baselines.source_based(items, 4, 1)), 6)),
        ("divergence of the first item", round(value(measures.mismatch(items.filter("item_id = 1"), edge)), 6)),
    ]
    return small(spark, rows, "measure string, bits_per_symbol double")


def bits_vs_books(spark: SparkSession, sf_dir: str, n_values=(3, 4, 5), k_values=range(1, 11), methods=("refine", "dc"), restarts: int = 2) -> DataFrame:
    """Bits against the number of books, for items uniform on the simplex; all k and restarts are runs of one sweep."""
    rows = []
    for n in n_values:
        items = even_points(spark, sf_dir, n)
        floor, base = value(measures.entropy_floor(items, n)), value(baselines.self_decodable(items, n))
        rows.append(("self-decodable", n, 0, 0, base, floor, base))
        for method in methods:
            runs = [Run(10 * k + r, Layout(k), r + 1) for k in k_values for r in range(restarts)]
            best: dict[int, Design] = {}
            for d in solve(items, n, runs, method):
                if d.run.layout.k0 not in best or d.cost < best[d.run.layout.k0].cost:
                    best[d.run.layout.k0] = d
            rows += [(method, n, k, k, ITEM_LENGTH * d.cost, floor, base) for k, d in sorted(best.items())]
    return report(spark, rows)


@query()
def w1_bits_vs_books(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As published: one to ten books, the published tolerance, and as many starts for both methods."""
    return bits_vs_books(spark, sf_dir)


_BASE = [
    f"SELECT {n}::INT AS n, round((SELECT 20 * sum(f * h) FROM (SELECT item_id, sum({PLOGP}) AS h FROM spv{n} GROUP BY 1) JOIN dem{n} USING (item_id)), 6) AS entropy_floor, "
    f"round((SELECT sum(f * b) FROM (SELECT item_id, sum(20 * ({PLOGP}) - log2(p)) AS b FROM spv{n} GROUP BY 1) JOIN dem{n} USING (item_id)), 6) AS self_decodable, round(20 * log2({n}), 6) AS fixed_length"
    for n in (3, 4, 5)
]


def _numbered(n: int) -> str:
    text = simplex_sql(n, 42, _PART_IDS)
    for name in ("ids", "raw", "spv", "dem"):
        text = text.replace(f"{name} AS (", f"{name}{n} AS (").replace(f"FROM {name}", f"FROM {name}{n}")
    return text


@query(with_(*(_numbered(n) for n in (3, 4, 5))) + " UNION ALL ".join(_BASE))
def w1_baselines(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for n in (3, 4, 5):
        items = even_points(spark, sf_dir, n)
        rows.append((n, round(value(measures.entropy_floor(items, n)), 6), round(value(baselines.self_decodable(items, n)), 6), round(baselines.fixed_length(n), 6)))
    return small(spark, rows, "n int, entropy_floor double, self_decodable double, fixed_length double")


@query()
def w1_empirical(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sweep on items of the given tables, whose SPVs are skewed and may lack symbols."""
    rows = []
    for name, n in (("events", 5), ("parts", 3), ("suppliers", 6), ("customers", 5)):
        items = fixture_items(spark, sf_dir, name)
        floor, base = value(measures.entropy_floor(items, n)), value(baselines.self_decodable(items, n, support_only=True))
        runs = [Run(10 * k + r, Layout(k), r + 1) for k in (1, 2, 4, 8) for r in range(2)]
        best: dict[int, float] = {}
        for d in solve(items, n, runs, mix=0.02):
            best[d.run.layout.k0] = min(best.get(d.run.layout.k0, float("inf")), ITEM_LENGTH * d.cost)
        rows += [(name, n, k, k, b, floor, base) for k, b in sorted(best.items())]
        rows.append((f"{name} source-based", n, 1, 1, value(baselines.source_based(items, n)), floor, base))
    return report(spark, rows)


def continuous(spark: SparkSession, density: str, size: int = 1000, grid: int = 60, restarts: int = 4) -> DataFrame:
    """Three symbols and two books: field iteration, both sampled designs and the search, all priced on one lattice."""
    points = fielditer.nodes(spark, 3, grid, density)
    engine = local_engine(collapse_types(points.select("item_id", "p", F.col("f").alias("w0"))), 3)
    weight = engine.w[:, 0]
    price = lambda q: ITEM_LENGTH * float(weight @ cross(engine.p, q).min(axis=1))
    floor = ITEM_LENGTH * float(weight @ engine.h)
    found = {
        "field iteration": best_of(fielditer.design(spark, density, 3, 2, grid, restarts)).q,
        "sampled, dc": best_of(sampled.design(spark, density, 3, 2, size, "dc", restarts=restarts)).q,
        "sampled, refine": best_of(sampled.design(spark, density, 3, 2, size, "refine", restarts=restarts)).q,
        "exhaustive": exhaustive.search(points, 20, 3)[0],
    }
    return report(spark, [(name, 3, 2, 2, price(q), floor, None) for name, q in found.items()])


@query()
def w2_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return continuous(spark, "uniform")


@query()
def w3_nonuniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return continuous(spark, "distance")


#: Chances of a common request, from none to one.
ALPHAS = (0.0, 0.25, 0.5, 0.75, 1.0)


def bits_vs_trace(spark: SparkSession, sf_dir: str, n: int, alphas=ALPHAS, kt: int = 4, methods=("refine", "dc"), restarts: int = 2) -> DataFrame:
    """Two users: total bits against the chance of a common request; all demands, layouts and starts of a method are one sweep."""
    points = part_points(spark, sf_dir, n, 42).persist()
    problems = {alpha: pair.even_channels(points, alpha) for alpha in alphas}
    base = {alpha: value(baselines.self_decodable_pair(items, n)) for alpha, items in problems.items()}
    rows = [(n, alpha, "self-decodable", 0, round(base[alpha], 6), 0.0) for alpha in alphas]
    for method in methods:
        found = {alpha: pair.select(designs) for alpha, designs in pair.design_sweep({a: x for a, x in problems.items() if a}, n, kt, kt, method, restarts).items()}
        if 0.0 in problems:  # nobody ever asks for what the other does: books of their own only
            found = {0.0: best_of(solve(problems[0.0], n, [Run(r, Layout(0, kt, kt), r + 1) for r in range(restarts)], method))} | found
        for alpha, d in found.items():
            bits = ITEM_LENGTH * d.cost
            rows.append((n, alpha, method, d.run.layout.k0, round(bits, 6), round(100 * (1 - bits / base[alpha]), 6)))
    points.unpersist()
    return small(spark, rows, "n int, trace double, method string, k0 int, bits_per_request double, saving_pct double")


@query()
def w4_bits_vs_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bits_vs_trace(spark, sf_dir, 3).unionByName(bits_vs_trace(spark, sf_dir, 5))


@query(
    with_(simplex_sql(5, 42, _PART_IDS), f"own AS (SELECT item_id, sum(20 * ({PLOGP}) - log2(p)) AS b FROM spv GROUP BY item_id)", "pts AS (SELECT a.alpha AS x, sum((2 - a.alpha) * f * b) AS y FROM own JOIN dem USING (item_id), (VALUES (0.0), (0.25), (0.5), (0.75), (1.0)) a(alpha) GROUP BY 1)")
    + "SELECT 'self-decodable' AS method, round(regr_slope(y, x), 5) AS slope, round(regr_intercept(y, x), 5) AS intercept, round(regr_r2(y, x), 6) AS r2 FROM pts"
)
def trace_linearity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prefbook.queries.designs import self_decodable_by_alpha

    points = self_decodable_by_alpha(part_points(spark, sf_dir, 5, 42), 5).select(F.lit("self-decodable").alias("method"), F.col("alpha").alias("trace"), "bits_per_request")
    fit = measures.trace_fit(points, ["method"])
    return fit.select("method", F.round("slope", 5).alias("slope"), F.round("intercept", 5).alias("intercept"), F.round("r2", 6).alias("r2"))


@query()
def w4_linearity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(measures.trace_fit(bits_vs_trace(spark, sf_dir, 3, methods=("refine",)), ["method"]), "slope", "intercept", "r2")


def interest_items(points: DataFrame, common: float = 0.2) -> DataFrame:
    """Channels of two users with interests in overlapping half-simplices, and a diagonal part on what both like."""
    one, two = (F.col("p")[0] > 0.3).cast("double"), (F.col("p")[1] > 0.3).cast("double")
    marked = points.select("item_id", "p", one.alias("m1"), two.alias("m2"), (one * two).alias("m0"))
    totals = marked.agg(*(F.sum(f"m{i}").alias(f"t{i}") for i in range(3)))
    shares = marked.crossJoin(F.broadcast(totals)).select("item_id", "p", *((F.col(f"m{i}") / F.greatest(F.lit(1e-300), F.col(f"t{i}"))).alias(f"s{i}") for i in range(3)))
    both = F.col("s1") * F.col("s2")
    return shares.select("item_id", "p", (common * F.col("s0") + (1 - common) * both).alias("w0"), ((1 - common) * (F.col("s1") - both)).alias("w1"), ((1 - common) * (F.col("s2") - both)).alias("w2"))


@query()
def w5_distinct_interests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where the books of two users with distinct interests lie: margin 0 is the border between them."""
    items = interest_items(part_points(spark, sf_dir, 3, 42))
    engine = local_engine(collapse_types(items), 3)
    sides = [w @ engine.p / w.sum() for w in (engine.w[:, 1], engine.w[:, 2])]
    rows = []
    for method in ("refine", "dc"):
        d = pair.select(pair.design(items, 3, 4, 4, method))
        margins = measures.border_distance(d.q, *sides)
        rows += [(method, d.run.layout.k0, int(pool), k, round(float(m), 6), round(ITEM_LENGTH * d.cost, 6)) for k, (pool, m) in enumerate(zip(d.run.layout.pools, margins))]
    return small(spark, rows, "method string, k0 int, pool int, book int, margin double, bits_per_request double")


_ROLES = """turns AS (SELECT conv_id, turn, role, least(9, floor(length(text) / 100))::BIGINT AS item FROM conversations),
jc AS (SELECT a.item AS i, b.item AS j, count(*)::DOUBLE AS c FROM turns a JOIN turns b ON a.conv_id = b.conv_id AND a.turn + 1 = b.turn AND a.role = 'user' AND b.role = 'assistant' GROUP BY 1, 2),
joint AS (SELECT i, j, c / sum(c) OVER () AS f FROM jc)"""


@query(with_(_ROLES, _CHANNELS) + "SELECT item_id, round(w0, 6) AS w0, round(w1, 6) AS w1, round(w2, 6) AS w2 FROM ch")
def w5_conversation_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joint demand of roles: items are length classes of a user turn and of the next assistant turn."""
    turns = load(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.least(F.lit(9), F.floor(F.char_length("text") / 100)).cast("long").alias("item"))
    asked, told = turns.filter("role = 'user'").alias("a"), turns.filter("role = 'assistant'").alias("b")
    both = asked.join(told, (F.col("a.conv_id") == F.col("b.conv_id")) & (F.col("a.turn") + 1 == F.col("b.turn")))
    counts = both.groupBy(F.col("a.item").alias("i"), F.col("b.item").alias("j")).agg(F.count("*").cast("double").alias("c"))
    total = counts.agg(F.sum("c").alias("t"))
    joint = counts.crossJoin(F.broadcast(total)).select("i", "j", (F.col("c") / F.col("t")).alias("f"))
    return rounded(pair.channels(joint), "w0", "w1", "w2")


@query()
def w6_cohort_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trace and cost of two cohorts' requests by week, items being event types: the more in common, the fewer bits."""
    log = pair.cohort_log(request_log(spark, sf_dir), "item_id").withColumn("week", F.weekofyear("ts")).persist()
    spvs = fixture_spv(spark, sf_dir, "events").select("item_id", "p")
    weeks = sorted(r["week"] for r in log.select("week").distinct().collect())  # at most 53
    problems = {w: pair.channels_by_bucket(log.filter(F.col("week") == w), F.date_trunc("day", "ts")).join(spvs, "item_id") for w in weeks}
    rows = []
    for week, designs in pair.design_sweep(problems, 5, 2, 2, "refine").items():
        d = pair.select(designs)
        trace = value(problems[week].agg(F.sum("w0")))
        rows.append((int(week), round(trace, 6), d.run.layout.k0, round(ITEM_LENGTH * d.cost, 6)))
    log.unpersist()
    return small(spark, rows, "week int, trace double, k0 int, bits_per_request double")


_SWEPT = with_(simplex_sql(3, 42, _PART_IDS), priced(3, 4)) + "SELECT a.alpha::DOUBLE AS trace, round(sum((2 - a.alpha) * 20 * f * c), 6) AS bits_per_request FROM best JOIN dem USING (item_id), (VALUES (0.0), (0.25), (0.5), (0.75), (1.0)) a(alpha) GROUP BY a.alpha"


@query(_SWEPT)
def w6_trace_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same claim on the two-level matrix, at fixed books."""
    points = part_points(spark, sf_dir, 3, 42)
    q = simplex.portable_books(3, 4)
    out = None
    for alpha in (0.0, 0.25, 0.5, 0.75, 1.0):
        row = pair.expected_bits(pair.even_channels(points, alpha), 3, Layout(4), q).select(F.lit(alpha).alias("trace"), F.round("bits_per_request", 6).alias("bits_per_request"))
        out = row if out is None else out.unionByName(row)
    return out


@query()
def w7_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Books designed on the requests of days 1 to 20, priced on those of days 21 to 30."""
    log = request_log(spark, sf_dir).withColumn("late", F.dayofmonth("ts") > 20)
    shares = log.groupBy("item_id").agg(F.count_if(~F.col("late")).cast("double").alias("f"), F.count_if("late").cast("double").alias("g"))
    items = shares.join(fixture_spv(spark, sf_dir, "events").select("item_id", "p"), "item_id").persist()
    past, future = items.select("item_id", "p", "f"), items.select("item_id", "p", F.col("g").alias("f"))
    floor, base = value(measures.entropy_floor(future, 5)), value(baselines.self_decodable(future, 5, support_only=True))
    rows = []
    for k in (1, 2, 4):
        runs = [Run(r, Layout(k), r + 1) for r in range(2)]
        for name, history in (("learned before", past), ("learned in hindsight", future)):
            rows.append((name, 5, k, k, value(measures.expected_bits(future, best_of(solve(history, 5, runs)).q)), floor, base))
    items.unpersist()
    return report(spark, rows)


@query()
def pair_trace_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly joint demand of two cohorts: full designs of both methods beside the self-decodable baseline."""
    items = pair_items(spark, sf_dir)
    base = value(baselines.self_decodable_pair(items, 5, support_only=True))
    rows = [("self-decodable", 0, round(base, 6))]
    for method in ("refine", "dc"):
        d = pair.select(pair.design(items, 5, 3, 3, method))
        rows.append((method, d.run.layout.k0, round(ITEM_LENGTH * d.cost, 6)))
    return small(spark, rows, "method string, k0 int, bits_per_request double")




@query()
def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Designs and baselines on the items of the request log, in one report."""
    items = fixture_items(spark, sf_dir, "events").persist()
    floor, base = value(measures.entropy_floor(items, 5)), value(baselines.self_decodable(items, 5, support_only=True))
    rows = [
        ("single codebook", 5, 1, 1, value(measures.expected_bits(items, single.book(items, 5))), floor, base),
        ("source-based", 5, 1, 1, value(baselines.source_based(items, 5)), floor, base),
        ("fixed length", 5, 1, 1, baselines.fixed_length(5), floor, base),
        ("self-decodable", 5, 0, 0, base, floor, base),
        ("entropy floor", 5, 0, 0, floor, floor, base),
    ]
    for method in ("refine", "dc"):
        d = best_of(solve(items, 5, [Run(r, Layout(4), r + 1) for r in range(2)], method, **({"mix": 0.02} if method == "refine" else {})))
        rows.append((method, 5, 4, 4, ITEM_LENGTH * d.cost, floor, base))
    items.unpersist()
    return report(spark, rows)
