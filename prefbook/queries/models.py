"""Items, demand, edge law, codebooks in closed form, assignment."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.operators import assign, demand, simplex, single, spv, verify
from prefbook.queries.fragments import collapsed, lattice, priced, requests, seeded, with_
from prefbook.queries.fragments import simplex as simplex_sql
from prefbook.queries.fragments import spv as spv_sql
from prefbook.queries.fragments import uniform as u_sql
from prefbook.queries.registry import query, r6, rounded
from prefbook.sources.tables import FIXTURES, fixture_demand, fixture_items, fixture_spv, load, requests as request_log

_LONG = "SELECT item_id, t::BIGINT AS n_sym, n::INT AS n, round(p, 6) AS p FROM spv JOIN tot USING (item_id)"
K = 4


def long(df: DataFrame) -> DataFrame:
    return rounded(spv.exploded(df), "p")


def numbers(name: str) -> int:
    return len(FIXTURES[name].alphabet)


@query(with_(spv_sql("events")) + _LONG)
def spv_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(fixture_spv(spark, sf_dir, "events"))


@query(with_(spv_sql("parts")) + _LONG)
def spv_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(fixture_spv(spark, sf_dir, "parts"))


@query(with_(spv_sql("suppliers")) + _LONG)
def spv_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(fixture_spv(spark, sf_dir, "suppliers"))


@query(with_(spv_sql("customers")) + _LONG)
def spv_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(fixture_spv(spark, sf_dir, "customers"))


_DOC_COUNTS = """
cnts AS (SELECT doc_id AS item_id, length(text)::DOUBLE AS t, [length(regexp_replace(text, '[^aeiouAEIOU]', '', 'g')), length(regexp_replace(text, '[^bcdfghjklmnpqrstvwxyzBCDFGHJKLMNPQRSTVWXYZ]', '', 'g')),
    length(regexp_replace(text, '[^0-9]', '', 'g')), length(regexp_replace(text, '[^ \\t\\n\\r\\f\\x0B]', '', 'g'))] AS c FROM documents WHERE length(text) > 0),
docspv AS (SELECT item_id, t::BIGINT AS n_sym, unnest(range(5)) AS n, unnest(list_append(c, (t - list_sum(c))::BIGINT))::DOUBLE / t AS p FROM cnts)"""


@query(with_(_DOC_COUNTS) + "SELECT item_id, n_sym, n::INT AS n, round(p, 6) AS p FROM docspv")
def spv_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(spv.from_text(load(spark, sf_dir, "documents"), "doc_id", "text"))


@query(
    "WITH raw AS (SELECT vec_id, unnest(range(64)) AS n, unnest(embedding)::DOUBLE AS v FROM embeddings), top AS (SELECT *, max(v) OVER (PARTITION BY vec_id) AS m FROM raw) "
    "SELECT vec_id AS item_id, 64::BIGINT AS n_sym, n::INT AS n, round(exp(v - m) / sum(exp(v - m)) OVER (PARTITION BY vec_id), 6) AS p FROM top"
)
def spv_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(spv.from_vector(load(spark, sf_dir, "embeddings"), "vec_id", "embedding"))


@query(
    "WITH w AS (SELECT item_id, unnest(regexp_extract_all(text, '[a-z]+')) AS symbol FROM benchmark), c AS (SELECT item_id, symbol, count(*) AS cnt FROM w GROUP BY 1, 2) "
    "SELECT item_id, symbol, cnt::BIGINT AS cnt, round(cnt / sum(cnt) OVER (PARTITION BY item_id), 6) AS p FROM c"
)
def spv_words_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = load(spark, sf_dir, "benchmark").withColumn("w", F.regexp_extract_all("text", F.lit("[a-z]+"), F.lit(0)))
    return rounded(spv.long_form(words, "item_id", "w"), "p")


_F = "SELECT item_id, round(f, 6) AS f FROM dem"


@query(with_(spv_sql("events")) + _F)
def demand_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(demand.empirical(request_log(spark, sf_dir)), "f")


@query(with_(requests()) + "SELECT user_id, item_id, round(count(*) / sum(count(*)) OVER (PARTITION BY user_id), 6) AS f FROM req GROUP BY user_id, item_id")
def demand_by_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(demand.empirical(request_log(spark, sf_dir), user="user_id"), "f")


@query(with_(spv_sql("parts")) + _F)
def demand_quantity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(fixture_demand(spark, sf_dir, "parts"), "f")


@query(with_(spv_sql("events")) + "SELECT n::INT AS n, round(sum(f * p), 6) AS p FROM spv JOIN dem USING (item_id) GROUP BY n")
def edge_distribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(demand.edge_distribution(fixture_items(spark, sf_dir, "events"), 5))


@query(
    with_(spv_sql("events"), requests(), "fu AS (SELECT user_id, item_id, count(*) / sum(count(*)) OVER (PARTITION BY user_id) AS f FROM req GROUP BY 1, 2)")
    + "SELECT user_id, n::INT AS n, round(sum(fu.f * p) / sum(fu.f), 6) AS p FROM fu JOIN spv USING (item_id) GROUP BY user_id, n"
)
def edge_distribution_by_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = demand.empirical(request_log(spark, sf_dir), user="user_id")
    return long(demand.edge_distribution(own.join(fixture_spv(spark, sf_dir, "events"), "item_id"), 5, "user_id"))


_PRICED = with_(spv_sql("parts"), priced(3, K))


@query(_PRICED + "SELECT item_id, k::INT AS k, round(20 * c, 6) AS bits, round(c - h, 6) AS divergence FROM cost JOIN ent USING (item_id)")
def item_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = assign.divergences(fixture_spv(spark, sf_dir, "parts").select("item_id", "p"), simplex.portable_books(3, K))
    return pairs.select("item_id", "k", r6(20 * F.col("cost")).alias("bits"), r6("divergence").alias("divergence"))


_NEAREST = "SELECT item_id, k::INT AS k, round(c - h, 6) AS divergence FROM best JOIN ent USING (item_id)"


@query(_PRICED + _NEAREST)
def assign_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign.nearest(fixture_spv(spark, sf_dir, "parts"), simplex.portable_books(3, K)).select("item_id", "k", r6("divergence").alias("divergence"))


@query(_PRICED + "SELECT item_id, k::INT AS k FROM best")
def assign_halfspace(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign.by_halfspace(fixture_spv(spark, sf_dir, "parts"), simplex.portable_books(3, K)).select("item_id", "k")


_SINGLE = "SELECT n::INT AS n, round(sum(f * p) / sum(sum(f * p)) OVER (), 6) AS q FROM spv JOIN dem USING (item_id) GROUP BY n"


@query(with_(spv_sql("events")) + _SINGLE)
def single_codebook(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(spv.exploded(single.optimal(fixture_items(spark, sf_dir, "events"), 5), "q", "q"), "q")


@query(with_(spv_sql("events")) + _SINGLE)
def single_codebook_decimal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(spv.exploded(single.optimal(fixture_items(spark, sf_dir, "events"), 5, exact=True), "q", "q"), "q")


@query(with_(spv_sql("events")) + "SELECT n::INT AS n, round(-log2(sum(f * p) / sum(sum(f * p)) OVER ()), 6) AS bits FROM spv JOIN dem USING (item_id) GROUP BY n")
def single_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(spv.exploded(single.lengths(single.optimal(fixture_items(spark, sf_dir, "events"), 5)).select("bits"), "bits", "bits"), "bits")


@query(
    _PRICED.rstrip() + ",\nmeans AS (SELECT k, n, sum(f * p) / sum(sum(f * p)) OVER (PARTITION BY k) AS m FROM spv JOIN best USING (item_id) JOIN dem USING (item_id) GROUP BY k, n)\n"
    "SELECT k::INT AS k, round(max(abs(m - q)), 6) AS residual FROM means JOIN books USING (k, n) GROUP BY k"
)
def fixed_point_residual(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(verify.fixed_point(fixture_items(spark, sf_dir, "parts"), simplex.portable_books(3, K)), "residual")


@query(_PRICED.rstrip() + "\nSELECT k::INT AS k, n::INT AS n, round(sum(f * p) / sum(sum(f * p)) OVER (PARTITION BY k), 6) AS q FROM spv JOIN best USING (item_id) JOIN dem USING (item_id) GROUP BY k, n")
def region_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    means = single.optimal(assign.nearest(fixture_items(spark, sf_dir, "parts"), simplex.portable_books(3, K)), 3, by=["k"])
    return rounded(spv.exploded(means, "q", "q"), "q")


#: Items of the published simulations.
POINTS = 1000
_PART_IDS = f"SELECT i AS item_id FROM range(1, {POINTS} + 1) r(i)"


def part_points(spark: SparkSession, sf_dir: str, n: int, seed: int) -> DataFrame:
    """Items uniform on the simplex, as many as published: points are generated from a range of numbers."""
    return simplex.uniform_points(spark.range(1, POINTS + 1).withColumnRenamed("id", "item_id"), n, seed)


_POINTS = "SELECT item_id, n::INT AS n, round(p, 6) AS p FROM spv"


@query(with_(simplex_sql(5, 42, _PART_IDS)) + _POINTS)
def simplex_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return long(part_points(spark, sf_dir, 5, 42))


@query(
    with_(spv_sql("parts"), f"dist AS (SELECT item_id, sqrt(sum(pow(p - 1.0 / 3, 2))) AS d FROM spv GROUP BY item_id), kept AS (SELECT item_id, d FROM dist WHERE {u_sql(chr(39) + '43' + chr(39), 'item_id', '999')} * sqrt(1 - 1.0 / 3) <= d)")
    + "SELECT item_id, round(d, 6) AS d FROM kept"
)
def simplex_rejection(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sample of the parts by a density at their SPVs, by rejection."""
    return simplex.reject(fixture_spv(spark, sf_dir, "parts"), 3, "distance", 43).select("item_id", r6(simplex.distance(F.col("p"), 3)).alias("d"))


@query(
    with_(
        spv_sql("parts"),
        lattice(12, "cell"),
        "sides AS (SELECT item_id, 12 * max(p) FILTER (n = 0) AS u, 12 * max(p) FILTER (n = 1) AS v FROM spv GROUP BY item_id)",
        "lower AS (SELECT *, least(floor(v), 11 - a) AS b FROM (SELECT *, least(floor(u), 11) AS a FROM sides))",
        "held AS (SELECT ((CASE WHEN (u - a) + (v - b) > 1 AND a + b < 11 THEN 144 ELSE 0 END) + 12 * a + b)::BIGINT AS item_id, count(*) AS items FROM lower GROUP BY 1)",
    )
    + "SELECT item_id, coalesce(items, 0)::BIGINT AS items, n::INT AS n, round(p, 6) AS p FROM cell LEFT JOIN held USING (item_id)"
)
def simplex_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Equal cells of the triangle, with the number of parts whose SPVs they hold."""
    held = fixture_spv(spark, sf_dir, "parts").groupBy(simplex.cell(F.col("p"), 12).alias("item_id")).agg(F.count("*").alias("items"))
    cells = simplex.lattice(spark, 12).join(F.broadcast(held), "item_id", "left")  # at most grid * grid rows
    return long(cells.select("item_id", F.coalesce("items", F.lit(0)).alias("items"), "p"))


@query(with_(spv_sql("parts"), collapsed(), *seeded(1, 1, 2)) + "SELECT item_id, n::INT AS n, round(p, 6) AS p FROM tspv JOIN w0 USING (item_id)")
def seed_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prefbook.functions.uniform import race_key

    types = spv.collapse_types(fixture_items(spark, sf_dir, "parts"))
    key = race_key(1, F.col("item_id"), 1, F.col("f"))
    won = types.withColumn("key", key).filter("key is not null").agg(F.min_by(F.struct("item_id", "p"), F.struct("key", "item_id")).alias("w"))
    return long(won.select("w.item_id", "w.p"))


