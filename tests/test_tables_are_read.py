"""Queries whose jobs are on given tables: they read them whole, and agree with plain counts of them."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from prefbook.functions.uniform import uniform
from prefbook.operators import baselines, codec, exhaustive, measures, simplex
from prefbook.queries import QUERIES
from prefbook.sources.tables import fixture_items, fixture_spv, load


def reads(spark, folder, name, *tables):
    """The rows of a query, whose plan has to scan the tables."""
    rows = QUERIES[name](spark, folder)
    files = {f.split("/")[-1].split("?")[0] for f in rows.inputFiles()}
    assert {f"{t}.parquet" for t in tables} <= files, files
    return rows


def test_code_tables(spark, small):
    rows = reads(spark, small, "code_table", "orders").toPandas()
    own = {r.item_id: r.p for r in fixture_spv(spark, small, "customers").collect()}
    assert set(rows.item_id) == set(own) and len(rows) == sum(x > 0 for p in own.values() for x in p)
    for item, words in rows.groupby("item_id"):
        assert {r.symbol: (r.code_bits, r.codeword) for r in words.itertuples()} == codec.integer_code(own[item])


def test_codes_of_empty_and_single_books(spark):
    books = spark.createDataFrame([(1, [0.0, 1.0]), (2, [0.5, 0.5])], "item_id long, p array<double>")
    got = [tuple(r) for r in codec.code_tables(books).orderBy("item_id", "symbol").collect()]
    assert got == [(1, 1, 0.0, 1, "0"), (2, 0, 1.0, 1, "0"), (2, 1, 1.0, 1, "1")]
    assert codec.code_tables(books.filter("item_id > 2")).count() == 0


def test_huffman_code_tables(spark, small):
    rows = reads(spark, small, "code_table_huffman", "orders").toPandas()
    own = {r.item_id: r.p for r in fixture_spv(spark, small, "customers").collect()}
    assert set(rows.item_id) == set(own) and len(rows) == sum(x > 0 for p in own.values() for x in p)
    for item, words in rows.groupby("item_id"):
        assert {r.symbol: (r.code_bits, r.codeword) for r in words.itertuples()} == codec.integer_code(own[item], "huffman")


def test_demo_items(spark, small):
    rows = reads(spark, small, "demo_items", "orders").toPandas()
    orders = load(spark, small, "orders").toPandas()
    share = pd.crosstab(orders.o_custkey, orders.o_orderdate.dt.quarter, normalize="index")
    got = rows.pivot(index="item_id", columns="quarter", values="p")
    assert list(got.columns) == ["Q1", "Q2", "Q3", "Q4"] and list(got.index) == list(share.index) and len(rows) == 4 * len(share)
    assert abs(got.to_numpy() - share.to_numpy()).max() <= 1e-6 and (got == 0).any(axis=None)


@pytest.mark.parametrize("name, density", [("exhaustive_nonuniform", "distance"), ("exhaustive_uniform", "uniform")])
def test_all_pairs_on_all_parts(spark, small, name, density):
    rows = reads(spark, small, name, "lineitem").toPandas().set_index(["a", "b"])["cost"]
    lines = load(spark, small, "lineitem").toPandas()
    p = pd.crosstab(lines.l_partkey, lines.l_returnflag, normalize="index")[["A", "N", "R"]].to_numpy()
    f = np.ones(len(p)) if density == "uniform" else np.sqrt(((p - 1 / 3) ** 2).sum(axis=1))
    books = {r.item_id: np.log2(r.p) for r in simplex.lattice(spark, 6).collect()}
    want = {(a, b): f @ np.minimum(-p @ books[a], -p @ books[b]) / f.sum() for a in books for b in books if a < b}
    assert set(rows.index) == set(want) and all(abs(rows[x] - want[x]) <= 1e-6 for x in want)


def test_pair_costs_of_no_points(spark):
    assert exhaustive.pair_costs(spark.createDataFrame([], "item_id long, p array<double>, f double"), 3).count() == 0


def test_field_nodes_hold_the_demand_near_them(spark, small):
    rows = reads(spark, small, "field_nodes", "orders").toPandas()
    nodes = rows.pivot(index="item_id", columns="n", values="p").to_numpy()
    items = fixture_items(spark, small, "quarters").toPandas()
    near = (-np.array(items.p.tolist()) @ np.log2(nodes).T).argmin(axis=1)
    want = np.bincount(near, items.f, len(nodes))
    assert nodes.shape == (400, 4) and abs(rows.drop_duplicates("item_id").sort_values("item_id").f.to_numpy() - want).max() <= 1e-6
    assert want.max() > 0.01 and abs(want.sum() - 1) < 1e-9


def test_fixed_length_of_the_symbols_that_occur(spark, small):
    rows = reads(spark, small, "fixed_length", "orders", "events", "lineitem").toPandas().set_index("fixture")
    orders, events, lines = (load(spark, small, t).toPandas() for t in ("orders", "events", "lineitem"))
    want = {"customers": orders.o_orderpriority.nunique(), "events": events.event_type.nunique(), "parts": lines.l_returnflag.nunique(), "suppliers": (lines.l_returnflag + lines.l_linestatus).nunique()}
    assert rows.n.to_dict() == want
    assert rows.bits_per_request.to_dict() == pytest.approx({k: baselines.fixed_length(n) for k, n in want.items()}, abs=1e-6)
    assert [r[0] for r in spark.range(3).orderBy("id").select(baselines.fixed_bits(F.col("id"))).collect()] == [0.0, 0.0, 20.0]


def test_index_overhead_of_users(spark, small):
    rows = reads(spark, small, "index_overhead", "events").toPandas().set_index("user_id")
    events = load(spark, small, "events").toPandas()
    assert rows.k.to_dict() == events.groupby("user_id").props.nunique().to_dict()
    assert all(r.k == 1 and r.bits == 0 or 2 ** (r.bits - 1) < r.k <= 2**r.bits for r in rows.itertuples())


def test_index_bits_at_powers_of_two(spark):
    counts = [0, 1, 2, 3, 4, 5, 8, 9, 2**29, 2**29 + 1, 2**48, 2**48 + 1]
    rows = spark.createDataFrame([(k,) for k in counts], "k long").select("k", measures.index_bits(F.col("k")).alias("bits"))
    assert {r.k: r.bits for r in rows.collect()} == {k: (k - 1).bit_length() if k else 0 for k in counts}


def test_kraft_sums_of_users(spark, small):
    rows = reads(spark, small, "kraft_sum", "events").toPandas().set_index("user_id")
    events = load(spark, small, "events").toPandas()
    own = pd.crosstab(events.props, events.event_type, normalize="index")
    for user, asked in events.groupby("user_id"):
        q = own.loc[asked.props].mean().to_numpy()
        assert rows.kraft_sum[user] == pytest.approx(1.0)
        assert rows.whole_bits[user] == pytest.approx(sum(2.0 ** -np.ceil(-np.log2(x) - 1e-12) for x in q if x > 0), abs=1e-6)
    assert len(rows) == events.user_id.nunique() and (rows.whole_bits < 1).any()


def test_self_decodable_pair_of_customers(spark, small):
    rows = reads(spark, small, "self_decodable_pair", "orders").toPandas().set_index("alpha").bits_per_request
    own = np.array(fixture_spv(spark, small, "customers").toPandas().p.tolist())
    logs = -np.log2(np.where(own > 0, own, 1.0))
    bits = (20 * own * logs + logs).sum(axis=1).mean()
    assert (own == 0).any() and rows.to_dict() == pytest.approx({a: (2 - a) * bits for a in (0.0, 0.25, 0.5, 0.75, 1.0)}, abs=1e-6)


def test_lattice_cells_hold_the_parts(spark, small):
    rows = reads(spark, small, "simplex_lattice", "lineitem").toPandas()
    parts = np.array(fixture_spv(spark, small, "parts").toPandas().p.tolist())
    assert len(rows) == 432 and rows[rows.n == 0]["items"].sum() == len(parts)
    assert rows[rows.n == 0].set_index("item_id")["items"].to_dict() == {k: sum(c == k for c in map(_cell, parts)) for k in rows.item_id}


def _cell(p, grid=12):
    """The same with loops: the first cell whose corners have the point between them."""
    u, v = p[0] * grid, p[1] * grid
    for a in range(grid):
        for b in range(grid - a):
            x, y = u - a, v - b
            if 0 <= x and 0 <= y and x + y <= 1 and (x < 1 or a == grid - 1) and (y < 1 or a + b == grid - 1):
                return a * grid + b
            if a + b < grid - 1 and x < 1 and y < 1 and x + y > 1:
                return (grid + a) * grid + b


def test_cells_hold_centres_corners_and_borders(spark):
    cells = simplex.lattice(spark, 12)
    assert cells.filter(simplex.cell(F.col("p"), 12) != F.col("item_id")).count() == 0
    points = [[1.0, 0.0, 0.0], [0.0, 1.0, 0.0], [0.0, 0.0, 1.0], [0.5, 0.5, 0.0], [1 / 3] * 3, [0.0, 0.5, 0.5], [0.7, 0.3, 0.0]]
    border = spark.createDataFrame([(p,) for p in points], "p array<double>").select("p", simplex.cell(F.col("p"), 12).alias("item_id"))
    inside = border.join(cells.withColumnRenamed("p", "centre"), "item_id").collect()
    assert len(inside) == len(points) and all(abs(x - y) <= 2 / 36 + 1e-9 for r in inside for x, y in zip(r.p, r.centre))


def test_parts_accepted_by_their_density(spark, middle):
    rows = reads(spark, middle, "simplex_rejection", "lineitem").toPandas().set_index("item_id").d
    parts = fixture_spv(spark, middle, "parts").toPandas()
    d = dict(zip(parts.item_id, np.sqrt(((np.array(parts.p.tolist()) - 1 / 3) ** 2).sum(axis=1))))
    kept = {i: x for i, x in d.items() if uniform(43, i, 999) * np.sqrt(2 / 3) <= x}
    assert set(rows.index) == set(kept) and 0 < len(kept) < len(d) and rows.to_dict() == pytest.approx(kept, abs=1e-6)
    assert np.mean(list(kept.values())) > np.mean(list(d.values()))
