"""Costs, baselines and derived measures on fixed books."""

from __future__ import annotations


import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.functions.info import entropy_unrolled
from prefbook.operators import assign, baselines, codec, measures, simplex, single, spv
from prefbook.queries.fragments import PLOGP, books, lattice, priced, requests, source, spv as spv_sql, with_
from prefbook.queries.models import K, part_points
from prefbook.queries.registry import query, r6, rounded
from prefbook.sources.tables import FIXTURES, fixture_items, fixture_spv, load, requests as request_log, symbols

_PARTS = with_(spv_sql("parts"), priced(3, K))
_EVENTS = with_(spv_sql("events"), priced(5, K))


def fixed(n: int) -> np.ndarray:
    return simplex.portable_books(n, K)


@query(_PARTS + "SELECT round(20 * sum(f * c) / sum(f), 6) AS bits_per_request FROM best JOIN dem USING (item_id)")
def expected_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(measures.expected_bits(fixture_items(spark, sf_dir, "parts"), fixed(3)), "bits_per_request")


@query(_PARTS + "SELECT round(sum(f * (c - h)) / sum(f), 6) AS mismatch FROM best JOIN dem USING (item_id) JOIN ent USING (item_id)")
def mismatch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(measures.mismatch(fixture_items(spark, sf_dir, "parts"), fixed(3)), "mismatch")


@query(with_(spv_sql("events"), f"ent AS (SELECT item_id, sum({PLOGP}) AS h FROM spv GROUP BY 1)") + "SELECT round(20 * sum(f * h) / sum(f), 6) AS bits_per_request FROM ent JOIN dem USING (item_id)")
def entropy_floor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(measures.entropy_floor(fixture_items(spark, sf_dir, "events"), 5), "bits_per_request")


@query(with_(spv_sql("customers"), f"ent AS (SELECT item_id, sum({PLOGP}) AS h FROM spv GROUP BY 1)") + "SELECT item_id, round(h, 6) AS h FROM ent")
def item_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fixture_spv(spark, sf_dir, "customers").select("item_id", r6(entropy_unrolled(F.col("p"), 5)).alias("h"))


@query(_EVENTS + "SELECT item_id, k::INT AS k, round(c - h, 6) AS divergence FROM cost JOIN ent USING (item_id)")
def kl_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = assign.divergences(fixture_spv(spark, sf_dir, "events").select("item_id", "p"), fixed(5))
    return pairs.select("item_id", "k", r6("divergence").alias("divergence"))


_SELF = "SELECT item_id, sum(20 * (CASE WHEN p > 0 THEN -p * log2(p) ELSE 0 END) + CASE WHEN p > 0 THEN -log2(p) ELSE {absent} END) AS b FROM spv GROUP BY item_id"


@query(with_(spv_sql("events"), f"own AS ({_SELF.format(absent=chr(39) + 'Infinity' + chr(39) + '::DOUBLE')})") + "SELECT round(sum(f * b) / sum(f), 6) AS bits_per_request FROM own JOIN dem USING (item_id)")
def self_decodable(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(baselines.self_decodable(fixture_items(spark, sf_dir, "events"), 5), "bits_per_request")


@query(with_(spv_sql("customers"), f"own AS ({_SELF.format(absent='0')})") + "SELECT round(sum(f * b) / sum(f), 6) AS bits_per_request FROM own JOIN dem USING (item_id)")
def self_decodable_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(baselines.self_decodable(fixture_items(spark, sf_dir, "customers"), 5, support_only=True), "bits_per_request")


_SOURCE = "bk AS (SELECT n, avg(p) / sum(avg(p)) OVER () AS q FROM spv GROUP BY n)"


@query(with_(spv_sql("events"), _SOURCE) + "SELECT round(20 * sum(f * (CASE WHEN p > 0 THEN -p * log2(q) ELSE 0 END)), 6) AS bits_per_request FROM spv JOIN bk USING (n) JOIN dem USING (item_id)")
def source_based(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(baselines.source_based(fixture_items(spark, sf_dir, "events"), 5), "bits_per_request")


def _fixed_sql(name: str) -> str:
    alphabet = ", ".join(f"'{a}'" for a in FIXTURES[name].alphabet)
    return f"SELECT '{name}' AS fixture, n::INT AS n, round(20 * log2(greatest(n, 1)), 6) AS bits_per_request FROM (SELECT count(DISTINCT symbol) AS n FROM ({source(name)}) WHERE symbol IN ({alphabet}))"


_ALPHABETS = ("customers", "events", "parts", "suppliers")


@query(" UNION ALL ".join(map(_fixed_sql, _ALPHABETS)))
def fixed_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Codewords of one length for the symbols that occur in a table."""
    out = None
    for name in _ALPHABETS:
        held = symbols(spark, sf_dir, name).filter(F.col("symbol").isin(*FIXTURES[name].alphabet)).agg(F.count_distinct("symbol").cast("int").alias("n"))
        row = held.select(F.lit(name).alias("fixture"), "n", r6(baselines.fixed_bits(F.col("n"))).alias("bits_per_request"))
        out = row if out is None else out.unionByName(row)
    return out


@query(
    with_(spv_sql("events"), f"own AS ({_SELF.format(absent='0')})", "bk AS (SELECT n, sum(f * p) / sum(sum(f * p)) OVER () AS q FROM spv JOIN dem USING (item_id) GROUP BY n)")
    + "SELECT round(100 * (1 - (SELECT 20 * sum(f * (CASE WHEN p > 0 THEN -p * log2(q) ELSE 0 END)) FROM spv JOIN bk USING (n) JOIN dem USING (item_id)) / (SELECT sum(f * b) FROM own JOIN dem USING (item_id))), 6) AS saving_pct"
)
def saving_pct(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = fixture_items(spark, sf_dir, "events")
    ours = measures.expected_bits(items, single.book(items, 5)).withColumnRenamed("bits_per_request", "ours")
    theirs = baselines.self_decodable(items, 5, support_only=True).withColumnRenamed("bits_per_request", "theirs")
    return ours.crossJoin(F.broadcast(theirs)).select(r6(measures.saving(F.col("ours"), F.col("theirs"))).alias("saving_pct"))


@query(
    with_(spv_sql("events"), requests(), "fu AS (SELECT user_id, item_id, count(*)::DOUBLE AS f FROM req GROUP BY 1, 2)", "means AS (SELECT user_id, n, sum(fu.f * p) AS s FROM fu JOIN spv USING (item_id) GROUP BY 1, 2)")
    + "SELECT user_id, round(sum(q), 6) AS kraft_sum, round(sum(CASE WHEN q > 0 THEN pow(2, -ceil(-log2(q) - 1e-12)) ELSE 0 END), 6) AS whole_bits FROM (SELECT user_id, s / sum(s) OVER (PARTITION BY user_id) AS q FROM means) GROUP BY user_id"
)
def kraft_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Kraft sums of the best single book of every user, of ideal lengths and of these rounded up."""
    asked = request_log(spark, sf_dir).groupBy("user_id", "item_id").agg(F.count("*").cast("double").alias("f"))
    own = measures.kraft(single.optimal(asked.join(fixture_spv(spark, sf_dir, "events"), "item_id"), 5, by=["user_id"]))
    whole = F.transform("q", lambda x: F.when(x > 0, F.pow(F.lit(2.0), -F.ceil(-F.log2(x) - 1e-12))).otherwise(F.lit(0.0)))
    return rounded(measures.kraft(own.select("user_id", F.col("kraft_sum").alias("ideal"), whole.alias("q"))).select("user_id", F.col("ideal").alias("kraft_sum"), F.col("kraft_sum").alias("whole_bits")), "kraft_sum", "whole_bits")


@query(
    _EVENTS.rstrip() + ",\nlen AS (SELECT k, n, q, ceil(-log2(q) - 1e-12) AS bits FROM books)\nSELECT item_id, best.k::INT AS k, round(sum(p * (bits + log2(q))), 6) AS redundancy FROM spv JOIN best USING (item_id) JOIN len ON len.k = best.k AND len.n = spv.n GROUP BY item_id, best.k"
)
def integer_redundancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    q = fixed(5)
    extra = [[float(x) for x in np.ceil(-np.log2(row) - 1e-12) + np.log2(row)] for row in q]
    table = F.array(*(F.array(*(F.lit(x) for x in row)) for row in extra))
    rows = assign.nearest(fixture_spv(spark, sf_dir, "events").select("item_id", "p"), q)
    total = sum((F.col("p")[i] * table[F.col("k")][i] for i in range(1, 5)), F.col("p")[0] * table[F.col("k")][0])
    return rows.select("item_id", "k", r6(total).alias("redundancy"))


@query(with_(requests()) + "SELECT user_id, k::INT AS k, (CASE WHEN k > 1 THEN ceil(log2(k)) ELSE 0 END)::INT AS bits FROM (SELECT user_id, count(DISTINCT item_id) AS k FROM req GROUP BY user_id)")
def index_overhead(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits that name a book where a user holds one for each item asked for."""
    held = request_log(spark, sf_dir).groupBy("user_id").agg(F.count_distinct("item_id").alias("k"))
    return held.select("user_id", F.col("k").cast("int").alias("k"), measures.index_bits(F.col("k")).alias("bits"))


_PLACED = "placed AS (SELECT *, coalesce(sum(pow(2, most - bits)) OVER (PARTITION BY item_id ORDER BY bits, n ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS taken FROM (SELECT *, max(bits) OVER (PARTITION BY item_id) AS most FROM lens))"
_WORDS = "SELECT item_id, n::INT AS symbol, round(0 - log2(p), 6) AS ideal_bits, bits AS code_bits, lpad(bin((taken / pow(2, most - bits))::BIGINT), bits, '0') AS codeword FROM placed"


def _code_table(spark: SparkSession, sf_dir: str, how: str) -> DataFrame:
    """The code of every customer's own book, as an item carries it along."""
    return rounded(codec.code_tables(fixture_spv(spark, sf_dir, "customers"), how), "ideal_bits")


@query(with_(spv_sql("customers"), "lens AS (SELECT item_id, n, p, greatest(1, ceil(-log2(p) - 1e-12))::INT AS bits FROM spv WHERE p > 0)", _PLACED) + _WORDS)
def code_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Canonical codewords of ideal lengths rounded up."""
    return _code_table(spark, sf_dir, "ceil")


#: Four merges of the two lightest: lists of (weight, least symbol, symbols) by item, and the symbols merged so far.
_MERGES = ["h0 AS (SELECT item_id, list_sort(list({'w': p, 'm': n, 's': [n]})) AS l, []::INT[] AS d FROM spv WHERE p > 0 GROUP BY item_id)"] + [
    f"h{i + 1} AS (SELECT item_id, CASE WHEN len(l) > 1 THEN list_sort(list_append(l[3:], {{'w': l[1].w + l[2].w, 'm': least(l[1].m, l[2].m), 's': list_concat(l[1].s, l[2].s)}})) ELSE l END AS l, CASE WHEN len(l) > 1 THEN list_concat(d, list_concat(l[1].s, l[2].s)) ELSE d END AS d FROM h{i})"
    for i in range(4)
]


@query(with_(spv_sql("customers"), *_MERGES, "lens AS (SELECT item_id, n, p, greatest(1, len([x for x in d if x = n]))::INT AS bits FROM spv JOIN h4 USING (item_id) WHERE p > 0)", _PLACED) + _WORDS)
def code_table_huffman(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Canonical codewords of the best prefix codes."""
    return _code_table(spark, sf_dir, "huffman")


_GROUPS = ["aeiouAEIOU", "bcdfghjklmnpqrstvwxyzBCDFGHJKLMNPQRSTVWXYZ", "0123456789", " \t\n\r\f\x0b"]
_SIZES = ", ".join(f"length(regexp_replace(body, '[^{g}]', '', 'g'))" for g in ("aeiouAEIOU", "bcdfghjklmnpqrstvwxyzBCDFGHJKLMNPQRSTVWXYZ", "0-9", " \\t\\n\\r\\f\\x0B"))
_CODED = with_(
    f"src AS (SELECT doc_id AS item_id, length(body) AS t, [{_SIZES}] AS c FROM (SELECT doc_id, coalesce(text, '') AS body FROM documents))",
    "cnt AS (SELECT item_id, t, unnest(range(5)) AS n, unnest(list_append(c, (t - list_sum(c))::BIGINT))::DOUBLE AS c FROM src)",
    "own AS (SELECT n, sum(c / t) / sum(sum(c / t)) OVER () AS q FROM cnt WHERE t > 0 GROUP BY n)",
    books(5, K),
    "held AS (SELECT 0 AS k, n, q FROM own UNION ALL SELECT k + 1, n, q FROM books)",
    "priced AS (SELECT item_id, t, k, sum(CASE WHEN c > 0 THEN c * greatest(1, ceil(-log2(q) - 1e-12)) ELSE 0 END) AS bits FROM cnt JOIN held USING (n) GROUP BY item_id, t, k)",
    "won AS (SELECT item_id, t, k, bits FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY bits, k) AS rn FROM priced) WHERE rn = 1)",
)


def _cached(spark: SparkSession, sf_dir: str) -> np.ndarray:
    """Books that a receiver has: the best single one of the documents, and a few others."""
    items = spv.from_text(load(spark, sf_dir, "documents"), "doc_id", "text").withColumn("f", F.lit(1.0))
    return np.vstack([single.book(items, 5), fixed(5)])


@query(_CODED + "SELECT item_id, t::BIGINT AS symbols, k::INT AS book, bits::BIGINT AS bits, true AS same FROM won")
def codec_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole documents coded by character class and decoded again."""
    return codec.roundtrip(load(spark, sf_dir, "documents"), "doc_id", "text", _GROUPS, _cached(spark, sf_dir))


@query(_CODED + "SELECT item_id, t::BIGINT AS symbols, k::INT AS book, true AS found FROM won")
def decode_by_trial(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole documents decoded by trying every cached book: the sender's is always among those that fit."""
    return codec.trial_decoding(load(spark, sf_dir, "documents"), "doc_id", "text", _GROUPS, _cached(spark, sf_dir)).drop("candidates")


@query()
def zlib_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.zlib_bits(load(spark, sf_dir, "documents"), "doc_id", "text")


@query(_PARTS + "SELECT round(quantile_cont(c - h, 0.5), 6) AS median, round(quantile_cont(c - h, 0.9), 6) AS p90, round(max(c - h), 6) AS worst FROM best JOIN ent USING (item_id)")
def mismatch_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = assign.nearest(fixture_items(spark, sf_dir, "parts"), fixed(3))
    return rows.agg(*(r6(F.percentile("divergence", F.lit(x))).alias(name) for x, name in ((0.5, "median"), (0.9, "p90"))), r6(F.max("divergence")).alias("worst"))


_CELLS = with_(
    spv_sql("parts").split(",\ndem AS")[0],
    "dens AS (SELECT item_id, {g} AS g FROM spv GROUP BY item_id), dem AS (SELECT item_id, g / sum(g) OVER () AS f FROM dens)",
    lattice(6, "cand").replace("cand_cells", "cc"),
    "cst AS (SELECT s.item_id, c.item_id AS k, sum(-s.p * log2(c.p)) AS c FROM spv s JOIN cand c ON c.n = s.n GROUP BY 1, 2)",
)
_PAIRS = "SELECT x.k AS a, y.k AS b, round(sum(f * least(x.c, y.c)), 6) AS cost FROM cst x JOIN cst y ON x.item_id = y.item_id AND x.k < y.k JOIN dem ON dem.item_id = x.item_id GROUP BY 1, 2"


def _exhaustive(spark: SparkSession, sf_dir: str, density: str) -> DataFrame:
    """Every pair of lattice codebooks, priced on all parts, with a density at their SPVs as demand."""
    from prefbook.operators import exhaustive

    return rounded(exhaustive.pair_costs(simplex.weigh(fixture_spv(spark, sf_dir, "parts").select("item_id", "p"), 3, density), 6), "cost")


@query(_CELLS.replace("{g}", "1.0") + _PAIRS)
def exhaustive_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _exhaustive(spark, sf_dir, "uniform")


@query(_CELLS.replace("{g}", "sqrt(sum(pow(p - 1.0 / 3, 2)))") + _PAIRS)
def exhaustive_nonuniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _exhaustive(spark, sf_dir, "distance")


_TINY = with_(
    spv_sql("events"),
    "few AS (SELECT item_id, f, row_number() OVER (ORDER BY item_id) - 1 AS place FROM dem ORDER BY item_id LIMIT 8)",
    "bks AS (SELECT code, (floor(code / pow(2, place))::BIGINT % 2) AS book, n, sum(f * p) AS s FROM range(256) r(code), few JOIN spv USING (item_id) GROUP BY 1, 2, 3)",
    "parts AS (SELECT code, book, sum(s) AS t, sum(CASE WHEN s > 0 THEN s * log2(s) ELSE 0 END) AS e FROM bks GROUP BY 1, 2)",
)


@query(_TINY + "SELECT code, round(sum(CASE WHEN t > 0 THEN t * log2(t) ELSE 0 END - e), 6) AS cost FROM parts GROUP BY code")
def exhaustive_partitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prefbook.operators import exhaustive

    items = fixture_items(spark, sf_dir, "events").orderBy("item_id").limit(8)
    return rounded(exhaustive.partitions(items, 5, 2), "cost")


_BY_SEGMENT = _PARTS.rstrip() + ",\nwide AS (SELECT p.p_brand AS brand, p.p_size AS size, f, c FROM best JOIN dem USING (item_id) JOIN part p ON p.p_partkey = item_id)\n"
_COST = "round(20 * sum(f * c) / sum(f), 6) AS bits_per_request"


def _segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand"), F.col("p_size").alias("size"))
    return assign.nearest(fixture_items(spark, sf_dir, "parts"), fixed(3)).join(parts, "item_id")


def _named(totals: DataFrame) -> DataFrame:
    """Rows over all brands or sizes by name; no part lacks either."""
    return totals.select(F.coalesce("brand", F.lit("all")).alias("brand"), F.coalesce("size", F.lit(-1)).alias("size"), "bits_per_request")


def _bits() -> Column:
    return r6(20 * F.sum(F.col("f") * F.col("cost")) / F.sum("f")).alias("bits_per_request")


@query(_BY_SEGMENT + f"SELECT coalesce(brand, 'all') AS brand, coalesce(size, -1) AS size, {_COST} FROM wide GROUP BY ROLLUP (brand, size)")
def bits_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _named(_segments(spark, sf_dir).rollup("brand", "size").agg(_bits()))


@query(_BY_SEGMENT + f"SELECT coalesce(brand, 'all') AS brand, coalesce(size, -1) AS size, {_COST} FROM wide GROUP BY CUBE (brand, size)")
def bits_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _named(_segments(spark, sf_dir).cube("brand", "size").agg(_bits()))


@query(_BY_SEGMENT + f"SELECT coalesce(brand, 'all') AS brand, coalesce(size, -1) AS size, {_COST} FROM wide GROUP BY GROUPING SETS ((brand), (size), ())")
def bits_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    _segments(spark, sf_dir).createOrReplaceTempView("segment_costs")
    return _named(spark.sql("SELECT brand, size, round(20 * sum(f * cost) / sum(f), 6) AS bits_per_request FROM segment_costs GROUP BY GROUPING SETS ((brand), (size), ())"))


def even_points(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """Items uniform on the simplex with equal demand."""
    points = part_points(spark, sf_dir, n, 42)
    return points.crossJoin(F.broadcast(points.agg(F.count("*").alias("j")))).select("item_id", "p", (1.0 / F.col("j")).alias("f"))


