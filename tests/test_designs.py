"""Designs: invariants, exact optima, published behaviour, and the same numbers from every strategy."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from prefbook.operators import assign, baselines, exhaustive, measures, pair, simplex, single, spv, verify
from prefbook.operators.codec import user_channels
from prefbook.operators.dcdescent import descend, split
from prefbook.operators.refine import Run, means, refine, seed_books
from prefbook.plans.engine import Layout, LocalEngine, SparkEngine
from prefbook.plans.planner import Limits, as_problem, best_of, choose, local_engine, solve
from prefbook.queries import QUERIES
from prefbook.sources.tables import fixture_items


@pytest.fixture(scope="module")
def points(spark):
    ids = spark.range(300).withColumnRenamed("id", "item_id")
    return simplex.uniform_points(ids, 3, 42).withColumn("f", F.lit(1.0 / 300)).persist()


@pytest.fixture(scope="module")
def events(spark, middle):
    return fixture_items(spark, middle, "events").persist()


def engine_of(items, n):
    return local_engine(spv.collapse_types(as_problem(items)), n)


@pytest.mark.parametrize("method", ["refine", "dc"])
def test_strategies_agree(points, method):
    runs = [Run(0, Layout(3), 1), Run(1, Layout(2), 2)]
    options = {"iterations": 4, "fixed": True} if method == "refine" else {"inner": 3, "outer": 2, "fixed": True}
    found = [solve(points, 3, runs, method, strategy, **options) for strategy in ("runs in tasks", "passes by expressions")]
    for a, b in zip(*found):
        assert np.allclose(a.q, b.q) and a.cost == pytest.approx(b.cost)
        assert [x[1] for x in a.trace] == pytest.approx([x[1] for x in b.trace])


def test_blocks_equal_expressions(points):
    q = simplex.portable_books(3, 4)
    engine = SparkEngine(as_problem(points), 3)
    plain = engine.hard({0: (Layout(2, 1, 1), q)})[0]
    from prefbook.plans.engine import hard_block

    blocks = engine._blocks({0: (Layout(2, 1, 1), q)}, lambda p, w, ids, x: hard_block(p, w, *x))[0]
    assert np.allclose(plain.t, blocks.t) and np.allclose(plain.s, blocks.s) and np.allclose(plain.cost, blocks.cost)


def test_partitions_don_t_matter(points):
    runs = [Run(0, Layout(3), 1)]
    books = [solve(points.repartition(k), 3, runs, "refine", "passes by expressions", iterations=3, fixed=True)[0].q for k in (1, 4, 16)]
    assert np.allclose(books[0], books[1]) and np.allclose(books[0], books[2])
    exact = [single.optimal(points.repartition(k), 3, exact=True).first()["q"] for k in (1, 4, 16)]
    assert exact[0] == exact[1] == exact[2]


def test_planner(points):
    assert choose(points, 3, 4).strategy == "runs in tasks"
    assert choose(points, 3, 4, Limits(cells=100)).strategy == "passes by expressions"
    assert choose(points, 3, 400, Limits(cells=100)).strategy == "passes over blocks"


@pytest.mark.parametrize("method", ["refine", "dc"])
def test_monotone_and_fixed_point(points, method):
    d = solve(points, 3, [Run(0, Layout(4), 1)], method)[0]
    values = [x[1] for x in d.trace]
    assert all(b <= a + 1e-9 for a, b in zip(values, values[1:]))
    assert np.allclose(d.q.sum(axis=1), 1.0) and (d.q >= 0).all()
    if method == "refine":
        assert max(r.residual for r in verify.fixed_point(points, d.q).collect()) < 1e-6


def test_bounds_and_more_books(points):
    floor = measures.entropy_floor(points, 3).first()[0]
    one = measures.expected_bits(points, single.book(points, 3)).first()[0]
    last = one + 1e-9
    for k in (1, 2, 4, 8):
        bits = 20 * best_of(solve(points, 3, [Run(r, Layout(k), r + 1) for r in range(3)])).cost
        assert floor <= bits <= last
        last = bits
    assert 20 * engine_of(points, 3).hard({0: (Layout(1), single.book(points, 3))})[0].cost.sum() == pytest.approx(one)


def test_single_book_beats_random_books(events):
    best = measures.expected_bits(events, single.book(events, 5)).first()[0]
    engine = engine_of(events, 5)
    rng = np.random.default_rng(1)
    for q in rng.dirichlet(np.ones(5), 1000):
        assert 20 * engine.hard({0: (Layout(1), q[None])})[0].cost.sum() >= best - 1e-9


def test_exact_optimum_bounds_designs(events):
    few = events.orderBy("item_id").limit(8).persist()
    total = few.agg(F.sum("f")).first()[0]
    best = exhaustive.partitions(few, 5, 2).agg(F.min("cost")).first()[0]
    for method in ("refine", "dc"):
        own = best_of(solve(few, 5, [Run(r, Layout(2), r + 1) for r in range(5)], method)).cost
        assert own >= best - 1e-9 and own <= best + 0.02 * total
    with pytest.raises(ValueError, match="at most 8"):
        exhaustive.partitions(events, 5, 2)


def test_rounding_to_the_nearest_is_never_worse(points):
    engine = engine_of(points, 3)
    for seed in range(3):
        soft = descend(engine, [Run(0, Layout(3), seed)], outer=5, fixed=True, rounding="nearest")[0]
        likely = descend(engine, [Run(0, Layout(3), seed)], outer=5, fixed=True, rounding="argmax")[0]
        assert soft.cost <= soft.trace[-1][1] + 1e-9 and likely.cost >= engine.w.sum() * 0


def test_split_is_a_difference(points):
    engine = engine_of(points, 3)
    sums = engine.soft({0: (Layout(2), 1, np.zeros(2), np.zeros((2, 3)))})[0]
    convex, concave = split(sums)
    own = sum((sums.s[b] * np.log2(sums.t[b] / sums.s[b])).sum() for b in range(2))
    assert convex - concave == pytest.approx(own)


def test_halfspaces_are_regions(points):
    q = simplex.portable_books(3, 4)
    a = {r.item_id: r.k for r in assign.nearest(points, q).collect()}
    b = {r.item_id: r.k for r in assign.by_halfspace(points, q).collect()}
    assert a == b and len(a) == 300
    assert {r.books for r in verify.regions(assign.nearest(points, q)).collect()} == {1}


def test_permuted_books_cost_the_same(points):
    q = simplex.portable_books(3, 4)
    assert measures.expected_bits(points, q).first()[0] == pytest.approx(measures.expected_bits(points, q[::-1]).first()[0])


@pytest.mark.parametrize("rows", [0, 1, 5])
def test_degenerate_problems(spark, rows):
    items = spark.createDataFrame([(i, [0.5, 0.5, 0.0], 1.0) for i in range(rows)], "item_id long, p array<double>, f double")
    for method in ("refine", "dc"):
        d = solve(items, 3, [Run(0, Layout(2), 1)], method)[0]
        assert np.isfinite(d.q).all() and d.cost == pytest.approx(float(rows))


def test_as_many_books_as_types_leave_no_mismatch(spark):
    items = spark.createDataFrame([(1, [1.0, 0.0], 0.5), (2, [0.25, 0.75], 0.5)], "item_id long, p array<double>, f double")
    d = best_of(solve(items, 2, [Run(r, Layout(2), r + 1) for r in range(3)]))
    assert measures.mismatch(items, d.q).first()[0] == pytest.approx(0.0, abs=1e-9)


def test_seeds_spread(points):
    seeds = seed_books(engine_of(points, 3), [Run(0, Layout(4), s) for s in (1,)])[0]
    assert len({tuple(s) for s in seeds}) == 4


def test_published_savings(spark, middle):
    rows = {(r.method, r.n, r.k): r for r in QUERIES["w1_bits_vs_books"](spark, middle).collect()}
    assert rows["refine", 5, 10].saving_pct == pytest.approx(22, abs=1.0)
    assert rows["dc", 5, 10].saving_pct == pytest.approx(22, abs=1.0)
    worse = {(n, k) for (m, n, k), r in rows.items() if m != "self-decodable" and r.saving_pct < 0}
    assert worse == {(3, 1)}
    for n, floor, carried, alone in ((3, 24.045, 30.537, 31.699), (4, 31.258, 41.838, 40.0), (5, 37.029, 52.057, 46.439)):
        r = rows["self-decodable", n, 0]
        assert r.entropy_floor == pytest.approx(floor, rel=0.015) and r.bits_per_request == pytest.approx(carried, rel=0.015)
        assert rows["refine", n, 1].bits_per_request == pytest.approx(alone, rel=0.005)


def test_published_continuous_costs(spark, middle):
    uniform = {r.method: r.bits_per_request for r in QUERIES["w2_uniform"](spark, middle).collect()}
    assert all(29.04 < b < 29.12 for b in uniform.values())
    for name in ("w2_uniform", "w3_nonuniform"):
        bits = {r.method: r.bits_per_request for r in QUERIES[name](spark, middle).collect()}
        assert bits["exhaustive"] <= min(bits.values()) + 1e-3


def test_published_pair_saving_and_linearity(spark, middle):
    rows = QUERIES["w4_bits_vs_trace"](spark, middle).collect()
    assert all(abs(r.saving_pct - 19) < 1.0 for r in rows if r.n == 5 and r.method != "self-decodable")
    for n in (3, 5):
        bits = [r.bits_per_request for r in rows if r.n == n and r.method == "refine"]
        assert bits == sorted(bits, reverse=True)
    assert all(r.r2 > 0.999 for r in QUERIES["w4_linearity"](spark, middle).collect())


def test_common_books_lie_on_the_border(spark, middle):
    rows = QUERIES["w5_distinct_interests"](spark, middle).collect()
    for method in ("refine", "dc"):
        own = [r for r in rows if r.method == method]
        assert max(abs(r.margin) for r in own if r.pool == 0) < min(abs(r.margin) for r in own if r.pool)


def test_pair_identities(spark, middle):
    joint = spark.createDataFrame([(0, 0, 0.3), (0, 1, 0.2), (1, 2, 0.4), (2, 0, 0.1)], "i long, j long, f double")
    w = {r.item_id: (r.w0, r.w1, r.w2) for r in pair.channels(joint).collect()}
    assert w[0] == pytest.approx((0.3, 0.2, 0.1)) and w[1] == pytest.approx((0.0, 0.4, 0.2)) and w[2] == pytest.approx((0.0, 0.1, 0.4))
    assert sum(map(sum, w.values())) == pytest.approx(2 - pair.trace(joint).first()[0])
    explicit = spark.createDataFrame([(i, j, 0.4 / 5 if i == j else 0.6 / 20) for i in range(5) for j in range(5)], "i long, j long, f double")
    ids = simplex.uniform_points(spark.range(5).withColumnRenamed("id", "item_id"), 3, 1)
    even = {r.item_id: (r.w0, r.w1, r.w2) for r in pair.even_channels(ids, 0.4).collect()}
    assert all(even[r.item_id] == pytest.approx((r.w0, r.w1, r.w2)) for r in pair.channels(explicit).collect())


def test_pair_region_sum_is_the_cost(spark, middle):
    cost = QUERIES["pair_region_cost"](spark, middle).agg(F.sum("cost")).first()[0]
    bits = QUERIES["pair_cost"](spark, middle).first()[0]
    from prefbook.queries.designs import pair_items

    items = pair_items(spark, middle)
    floor = items.agg(F.sum((F.col("w0") + F.col("w1") + F.col("w2")) * F.aggregate("p", F.lit(0.0), lambda s, x: s - F.when(x > 0, x * F.log2(x)).otherwise(0.0)))).first()[0]
    assert bits / 20 == pytest.approx(cost + floor, abs=1e-4)


def test_swapped_users_swap_pools(points):
    items = points.select("item_id", "p", F.lit(0.001).alias("w0"), (F.col("f") * F.col("p")[0]).alias("w1"), (F.col("f") * F.col("p")[1]).alias("w2"))
    swapped = items.select("item_id", "p", "w0", F.col("w2").alias("w1"), F.col("w1").alias("w2"))
    a, b = engine_of(items, 3), engine_of(swapped, 3)
    q = simplex.portable_books(3, 4)
    one = refine(a, [Run(0, Layout(2, 1, 1), 1)], iterations=5, fixed=True, start={0: q})[0]
    two = refine(b, [Run(0, Layout(2, 1, 1), 1)], iterations=5, fixed=True, start={0: q[[0, 1, 3, 2]]})[0]
    assert np.allclose(one.q, two.q[[0, 1, 3, 2]]) and one.cost == pytest.approx(two.cost)


def test_full_trace_is_one_user(points):
    both = pair.design(pair.even_channels(points.select("item_id", "p"), 1.0), 3, 3, 3)
    alone = best_of(solve(points, 3, [Run(i, Layout(3), r + 1) for i, r in enumerate(range(2))]))
    assert pair.select(both).cost == pytest.approx(alone.cost, rel=1e-3)


def test_separate_baseline_pays_more(spark, middle):
    rows = {r.design: r.bits_per_request for r in QUERIES["separate_unicast"](spark, middle).collect()}
    assert rows["shared"] < rows["separate"]
    zero = {r.design: r.bits_per_request for r in QUERIES["pair_separate"](spark, middle).collect()}
    assert zero["together"] == pytest.approx(zero["apart"], rel=0.01)


def test_wrong_demand_costs_more(spark, middle):
    rows = {r.books: r.bits_under_g for r in QUERIES["mismatched_demand"](spark, middle).collect()}
    assert rows["for g"] <= rows["for f"] + 1e-9


def test_channels_of_three_users():
    assert user_channels(2) == [(1, 2), (1,), (2,)] and len(user_channels(3)) == 7


def test_infinite_costs(spark):
    items = spark.createDataFrame([(1, [1.0, 0.0], 1.0), (2, [0.5, 0.5], 0.0)], "item_id long, p array<double>, f double")
    q = single.book(items, 2)
    assert q.tolist() == [[1.0, 0.0]] and measures.expected_bits(items, q).first()[0] == 0.0
    assert measures.expected_bits(items.withColumn("f", F.lit(0.5)), q).first()[0] == float("inf")
    assert baselines.self_decodable(items, 2).first()[0] == float("inf") and baselines.self_decodable(items, 2, support_only=True).first()[0] == 0.0


def test_local_engine_is_plain(points):
    engine = engine_of(points, 3)
    assert isinstance(engine, LocalEngine) and engine.total() == pytest.approx(1.0)
    assert np.allclose(engine.mean(), SparkEngine(as_problem(points), 3).mean())


def test_parallel_seeds(points):
    runs = [Run(0, Layout(4), 1)]
    a = solve(points, 3, runs, "refine", "runs in tasks", seeding="parallel")[0]
    b = solve(points, 3, runs, "refine", "passes by expressions", seeding="parallel")[0]
    assert a.cost == pytest.approx(b.cost) and a.q.shape == (4, 3)
    plus = best_of(solve(points, 3, [Run(r, Layout(4), r + 1) for r in range(3)]))
    assert a.cost < plus.cost * 1.05


def test_block_skipping(spark, middle):
    row = QUERIES["block_skipping"](spark, middle).first()
    assert row.same and row.decided > 0 and row.items_read < row.items


def test_two_users_as_a_case_of_many(points):
    from prefbook.operators import multiuser
    from prefbook.plans.engine import hard_block

    engine = engine_of(pair.even_channels(points.select("item_id", "p"), 0.4), 3)
    q = simplex.portable_books(3, 4)
    many = multiuser.sums(engine.p, engine.w, multiuser.SharedLayout(2, (((1, 2), 2), ((1,), 1), ((2,), 1))), q)
    two = hard_block(engine.p, engine.w, Layout(2, 1, 1), q)
    assert np.allclose(many.t, two.t) and np.allclose(many.s, two.s) and many.cost.sum() == pytest.approx(two.cost.sum())


def test_salted_joins(spark, points):
    from prefbook.operators.skew import salted_join, two_level_sum

    large = spark.range(3000).select((F.col("id") % 7 * (F.col("id") % 3)).alias("item_id"), F.col("id").alias("x"))
    small = points.select("item_id", "f").filter("item_id < 10")
    for how in ("inner", "left", "left_semi", "left_anti"):
        assert sorted(map(str, salted_join(large, small, "item_id", 8, how).collect())) == sorted(map(str, large.join(small, "item_id", how).collect()))
    assert sorted(two_level_sum(large, ["item_id"], "x").collect()) == sorted(large.groupBy("item_id").agg(F.sum("x").alias("x")).collect())


def test_profile(spark, points):
    from prefbook.plans.profile import profile

    result, figures = profile(spark, points.count)
    assert result == 300 and figures["jobs"] >= 1 and figures["seconds"] > 0


def test_stop_rules(points):
    engine = engine_of(points, 3)
    found = {stop: refine(engine, [Run(0, Layout(4), 1)], stop=stop)[0] for stop in ("cost", "books", "either")}
    moved = means(engine.hard({0: (Layout(4), found["books"].q)})[0], found["books"].q)
    assert np.abs(moved - found["books"].q).max() <= 1e-6
    assert len(found["cost"].trace) <= len(found["books"].trace) and len(found["either"].trace) <= len(found["cost"].trace)
    with pytest.raises(ValueError, match="never"):
        refine(engine, [Run(0, Layout(1), 1)], stop="never")


def test_common_requests_need_a_common_book(points):
    q = simplex.portable_books(3, 2)
    for alpha, finite in ((0.0, True), (0.5, False)):
        items = pair.even_channels(points, alpha)
        for engine in (engine_of(items, 3), SparkEngine(as_problem(items), 3)):
            assert np.isfinite(engine.hard({0: (Layout(0, 1, 1), q)})[0].cost.sum()) == finite
    designs = pair.design(pair.even_channels(points, 0.5), 3, 2, 2, zero=True)
    assert pair.select(designs).run.layout.k0 > 0


def test_a_sweep_is_its_problems(points):
    problems = {alpha: pair.even_channels(points, alpha) for alpha in (0.0, 0.5)}
    swept = pair.design_sweep(problems, 3, 2, 2, restarts=1)
    for alpha, items in problems.items():
        for a, b in zip(swept[alpha], pair.design(items, 3, 2, 2, restarts=1)):
            assert np.array_equal(a.q, b.q) and a.cost == b.cost


def test_wide_books_cost_no_more_than_fixed_length(spark, small, middle):
    for folder in (small, middle):
        assert QUERIES["refine_wide"](spark, folder).first().bits_per_request <= 120
