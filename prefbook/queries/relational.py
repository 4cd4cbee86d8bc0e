"""Scans, filters, joins, aggregations, windows, sets and functions around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from prefbook.functions import sqlfuncs
from prefbook.functions.uniform import hash_uniform as uniform_of
from prefbook.operators import assign, demand, spv
from prefbook.queries.fragments import books, priced, requests, spv as spv_sql, with_
from prefbook.queries.fragments import uniform as u_sql
from prefbook.queries.measures import fixed
from prefbook.queries.models import K
from prefbook.queries.registry import query, r6, rounded, small
from prefbook.sources.tables import EVENTS_SCHEMA, TABLES, fixture_demand, fixture_items, fixture_spv, load, requests as request_log

_PARTS = with_(spv_sql("parts"), priced(3, K))


def choices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign.nearest(fixture_items(spark, sf_dir, "parts"), fixed(3))


# --- scans, inline rows, SQL ---------------------------------------------------------------


@query(" UNION ALL ".join(f"SELECT '{t}' AS name, count(*)::BIGINT AS rows FROM {t}" for t in TABLES))
def scan_all_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in TABLES:
        row = load(spark, sf_dir, name).agg(F.count("*").alias("rows")).select(F.lit(name).alias("name"), "rows")
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT event_type, count(*)::BIGINT AS n, round(sum(value), 6) AS total FROM events GROUP BY event_type")
def scan_schema(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = spark.read.schema(EVENTS_SCHEMA).parquet(f"{sf_dir}/events.parquet")
    return events.groupBy("event_type").agg(F.count("*").alias("n"), r6(F.sum("value")).alias("total"))


#: The worked example of four items over four symbols.
DEMO = [(1, [0.75, 0.25, 0.0, 0.0]), (2, [0.25, 0.75, 0.0, 0.0]), (3, [0.0, 0.0, 0.75, 0.25]), (4, [0.0, 0.0, 0.25, 0.75])]


@query(with_(spv_sql("quarters")) + "SELECT item_id, n::INT AS n, quarter, round(p, 6) AS p FROM spv JOIN (VALUES (0, 'Q1'), (1, 'Q2'), (2, 'Q3'), (3, 'Q4')) names(n, quarter) USING (n)")
def demo_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items over four symbols, of which many lack some: customers by the quarters of their orders, with inline rows that name the symbols."""
    names = small(spark, [(n, f"Q{n + 1}") for n in range(4)], "n int, quarter string")
    rows = spv.exploded(fixture_spv(spark, sf_dir, "quarters").select("item_id", "p"))
    return rounded(rows.join(F.broadcast(names), "n").select("item_id", "n", "quarter", "p"), "p")


@query(
    with_(spv_sql("events"), books(5, K), "ent AS (SELECT item_id, sum(CASE WHEN p > 0 THEN -p * log2(p) ELSE 0 END) AS h FROM spv GROUP BY 1)", "bk AS (SELECT n, sum(f * p) / sum(sum(f * p)) OVER () AS q FROM spv JOIN dem USING (item_id) GROUP BY n)")
    + "SELECT item_id, round(sum(CASE WHEN p > 0 THEN -p * log2(q) ELSE 0 END) - any_value(h), 6) AS divergence FROM spv JOIN bk USING (n) JOIN ent USING (item_id) GROUP BY item_id"
)
def sql_single_codebook(spark: SparkSession, sf_dir: str) -> DataFrame:
    sqlfuncs.register(spark)
    fixture_items(spark, sf_dir, "events").createOrReplaceTempView("priced_items")
    mean = ", ".join(f"sum(f * p[{i}]) / sum(f)" for i in range(5))
    return spark.sql(f"WITH b AS (SELECT array({mean}) AS q FROM priced_items) SELECT item_id, round(kl_bits(p, q), 6) AS divergence FROM priced_items CROSS JOIN b")


# --- filters -------------------------------------------------------------------------------


@query("SELECT event_id, user_id, event_type FROM events WHERE event_type IN ('purchase', 'signup') AND value BETWEEN 10 AND 50 AND user_id IS NOT NULL AND props LIKE '%1%'")
def filter_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load(spark, sf_dir, "events")
    return events.filter(F.col("event_type").isin("purchase", "signup") & F.col("value").between(10, 50) & F.col("user_id").isNotNull() & F.col("props").like("%1%")).select("event_id", "user_id", "event_type")


@query(with_(spv_sql("parts"), "v AS (SELECT item_id, list(round(p, 6) ORDER BY n) AS v FROM spv GROUP BY item_id)") + "SELECT count(DISTINCT v)::BIGINT AS types, count(*)::BIGINT AS items FROM v")
def distinct_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = fixture_spv(spark, sf_dir, "parts").select(F.transform("p", lambda x: F.round(x, 6)).alias("v"))
    return vectors.agg(F.count_distinct("v").alias("types"), F.count("*").alias("items"))


@query(f"SELECT o_orderkey FROM orders WHERE {u_sql(chr(39) + '5' + chr(39), 'o_orderkey', '0')} < 0.1")
def hash_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").filter(uniform_of(5, F.col("o_orderkey"), 0) < 0.1).select("o_orderkey")


@query(f"SELECT o_orderkey, o_orderpriority FROM orders WHERE {u_sql(chr(39) + '6' + chr(39), 'o_orderkey', '0')} < CASE WHEN o_orderpriority = '1-URGENT' THEN 0.2 WHEN o_orderpriority = '5-LOW' THEN 0.01 ELSE 0.05 END")
def stratified_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    rate = F.when(F.col("o_orderpriority") == "1-URGENT", 0.2).when(F.col("o_orderpriority") == "5-LOW", 0.01).otherwise(0.05)
    return load(spark, sf_dir, "orders").filter(uniform_of(6, F.col("o_orderkey"), 0) < rate).select("o_orderkey", "o_orderpriority")


@query(with_(spv_sql("customers")) + "SELECT item_id, bool_and(p >= 0) AND abs(sum(p) - 1) <= 1e-9 AS valid FROM spv GROUP BY item_id")
def spv_valid(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = fixture_spv(spark, sf_dir, "customers")
    return rows.select("item_id", spv.valid(rows).alias("valid"))


# --- joins ---------------------------------------------------------------------------------


@query(with_(spv_sql("parts")) + "SELECT item_id, n::INT AS n, round(p, 6) AS p, round(f, 6) AS f FROM spv JOIN dem USING (item_id)")
def join_spv_demand(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(spv.exploded(fixture_items(spark, sf_dir, "parts")), "p", "f")


@query(_PARTS + "SELECT item_id, best.k::INT AS k, n::INT AS n, round(q, 6) AS q FROM best JOIN books USING (k)")
def join_assignment_books(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = choices(spark, sf_dir)
    joined = rows.select("item_id", "k").join(F.broadcast(assign.book_rows(rows, fixed(3)).select("k", "q")), "k")
    return rounded(spv.exploded(joined, "q", "q"), "q")


@query(_PARTS + "SELECT a.item_id, a.k::INT AS k FROM cost a JOIN cost b ON a.item_id = b.item_id AND a.c <= b.c GROUP BY a.item_id, a.k HAVING count(*) = 4")
def regions_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Regions by their definition: a book that no other beats."""
    pairs = assign.divergences(fixture_spv(spark, sf_dir, "parts").select("item_id", "p"), fixed(3)).select("item_id", "k", "cost")
    a, b = pairs.alias("a"), pairs.alias("b")
    held = a.join(b, (F.col("a.item_id") == F.col("b.item_id")) & (F.col("a.cost") <= F.col("b.cost")))
    return held.groupBy(F.col("a.item_id").alias("item_id"), F.col("a.k").alias("k")).agg(F.count("*").alias("m")).filter(F.col("m") == K).select("item_id", "k")


_REQUESTED = "SELECT DISTINCT l_partkey FROM lineitem WHERE l_quantity >= 50"


@query(f"WITH asked AS (SELECT l_partkey, sum(l_quantity) AS w FROM lineitem WHERE l_quantity >= 50 GROUP BY 1) SELECT p_partkey AS item_id, round(coalesce(w, 0), 6) AS f FROM part LEFT JOIN asked ON l_partkey = p_partkey")
def join_unrequested(spark: SparkSession, sf_dir: str) -> DataFrame:
    asked = load(spark, sf_dir, "lineitem").filter("l_quantity >= 50").groupBy("l_partkey").agg(F.sum("l_quantity").alias("w"))
    parts = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_id"))
    return parts.join(asked, F.col("item_id") == F.col("l_partkey"), "left").select("item_id", r6(F.coalesce("w", F.lit(0.0))).alias("f"))


@query(f"SELECT p_partkey AS item_id FROM part WHERE p_partkey IN ({_REQUESTED})")
def semi_requested(spark: SparkSession, sf_dir: str) -> DataFrame:
    asked = load(spark, sf_dir, "lineitem").filter("l_quantity >= 50").select("l_partkey")
    return load(spark, sf_dir, "part").join(asked, F.col("p_partkey") == F.col("l_partkey"), "left_semi").select(F.col("p_partkey").alias("item_id"))


@query("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def anti_unrequested(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").join(load(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


_CDF = "cdf AS (SELECT item_id, sum(f) OVER (ORDER BY item_id) AS hi, sum(f) OVER (ORDER BY item_id) - f AS lo FROM dem)"


def cumulative(items: DataFrame) -> DataFrame:
    """(item_id, f, lo, hi): cumulative demand in the order of ids, from sums of id ranges and sums within them."""
    ranged = items.withColumn("range", F.floor(F.col("item_id") / 4096))
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    starts = ranged.groupBy("range").agg(F.sum("f").alias("mass")).select("range", F.coalesce(F.sum("mass").over(before), F.lit(0.0)).alias("start"))
    within = Window.partitionBy("range").orderBy("item_id").rowsBetween(Window.unboundedPreceding, 0)
    return ranged.withColumn("own", F.sum("f").over(within)).join(starts, "range").select("item_id", "f", (F.col("start") + F.col("own") - F.col("f")).alias("lo"), (F.col("start") + F.col("own")).alias("hi"))


@query(with_(spv_sql("events"), _CDF, f"draws AS (SELECT i AS draw, {u_sql(chr(39) + '9' + chr(39), 'i', '0')} AS u FROM range(200) r(i))") + "SELECT draw, item_id FROM draws JOIN cdf ON u >= lo AND u < hi")
def inverse_cdf_draw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weighted draws by a range join, made an equi-join on buckets of the unit interval."""
    bounds = cumulative(fixture_demand(spark, sf_dir, "events")).withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") * 256), F.floor(F.col("hi") * 256))))
    draws = spark.range(200).select(F.col("id").alias("draw"), uniform_of(9, F.col("id"), 0).alias("u")).withColumn("bucket", F.floor(F.col("u") * 256))
    return draws.join(bounds, "bucket").filter("u >= lo and u < hi").select("draw", "item_id")


@query(
    with_(spv_sql("parts"), "seg AS (SELECT c_mktsegment AS segment, l_partkey AS item_id, sum(l_quantity) AS w FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1, 2)")
    + "SELECT segment, n::INT AS n, round(sum(w * p) / sum(w), 6) AS p FROM seg JOIN spv USING (item_id) GROUP BY segment, n"
)
def edge_distribution_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User, order, line and item in a chain: what the symbols look like on the way to each segment."""
    customers = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_mktsegment").alias("segment"))
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("item_id"), "l_quantity")
    own = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customers, F.col("o_custkey") == F.col("c_custkey")).groupBy("segment", "item_id").agg(F.sum("l_quantity").alias("f"))
    return rounded(spv.exploded(demand.edge_distribution(own.join(fixture_spv(spark, sf_dir, "parts"), "item_id"), 3, "segment")), "p")


@query(_PARTS + "SELECT item_id, k::INT AS k, (rn - 1)::INT AS place, round(c, 6) AS cost FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY c, k) AS rn FROM cost) WHERE rn <= 2")
def lateral_two_best(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two cheapest books of each item from a lateral subquery over its own costs."""
    fixture_spv(spark, sf_dir, "parts").createOrReplaceTempView("lateral_items")
    literal = ", ".join("array(" + ", ".join(f"{x!r}D" for x in row) + ")" for row in fixed(3).tolist())
    return spark.sql(
        f"SELECT item_id, best.k AS k, place, round(best.c, 6) AS cost FROM lateral_items, LATERAL (SELECT posexplode(slice(array_sort(transform(array({literal}), (b, k) -> struct({sqlfuncs.CROSS.format(p='p', q='b')} AS c, k AS k))), 1, 2)) AS (place, best))"
    )


# --- aggregations --------------------------------------------------------------------------


@query(with_(requests()) + "SELECT count(DISTINCT item_id)::BIGINT AS items, count(DISTINCT symbol)::BIGINT AS symbols, count(DISTINCT user_id)::BIGINT AS users FROM req")
def distinct_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return request_log(spark, sf_dir).agg(F.count_distinct("item_id").alias("items"), F.count_distinct("symbol").alias("symbols"), F.count_distinct("user_id").alias("users"))


@query()
def approximate_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return request_log(spark, sf_dir).agg(F.approx_count_distinct("item_id").alias("items"), F.approx_count_distinct("user_id").alias("users"))


@query("SELECT l_partkey AS item_id, " + ", ".join(f"count(*) FILTER (WHERE l_returnflag = '{s}')::BIGINT AS {s}" for s in "ANR") + " FROM lineitem GROUP BY 1")
def spv_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    wide = load(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("item_id")).pivot("l_returnflag", ["A", "N", "R"]).count()
    return wide.select("item_id", *(F.coalesce(c, F.lit(0)).alias(c) for c in "ANR"))


@query("SELECT l_partkey AS item_id, s.symbol AS symbol, count(*) FILTER (WHERE l_returnflag = s.symbol)::BIGINT AS cnt FROM lineitem, (VALUES ('A'), ('N'), ('R')) s(symbol) GROUP BY 1, 2")
def spv_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spv_pivot(spark, sf_dir).unpivot("item_id", ["A", "N", "R"], "symbol", "cnt")


@query(with_(spv_sql("suppliers")) + "SELECT item_id, n::INT AS n, round(p, 6) AS p FROM spv")
def spv_from_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spv.exploded(fixture_spv(spark, sf_dir, "suppliers").drop("n_sym")).withColumnRenamed("n", "symbol").filter("p > 0")
    return rounded(spv.exploded(spv.from_long(rows, 6)), "p")


@query("SELECT l_partkey AS item_id, count(*)::BIGINT AS n_sym FROM lineitem GROUP BY 1 HAVING count(*) >= 35")
def items_min_symbols(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("item_id")).agg(F.count("*").alias("n_sym")).filter("n_sym >= 35")


@query(
    with_(spv_sql("events"), priced(5, K), requests(), "dly AS (SELECT ts::DATE AS day, item_id, count(*) AS c FROM req GROUP BY 1, 2)", "pt AS (SELECT day, k, n, sum(dly.c * p) AS s FROM dly JOIN best USING (item_id) JOIN spv USING (item_id) GROUP BY 1, 2, 3)")
    + "SELECT k::INT AS k, n::INT AS n, round(sum(s) / sum(sum(s)) OVER (PARTITION BY k), 6) AS q FROM pt GROUP BY k, n"
)
def daily_partial_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sums by day and book add up to the update of all days, so a new day needs only its own rows."""
    chosen = assign.nearest(fixture_spv(spark, sf_dir, "events").select("item_id", "p"), fixed(5))
    days = request_log(spark, sf_dir).groupBy(F.to_date("ts").alias("day"), "item_id").agg(F.count("*").alias("c"))
    partial = days.join(chosen, "item_id").groupBy("day", "k").agg(*(F.sum(F.col("c") * F.col("p")[i]).alias(f"s{i}") for i in range(5)))
    merged = partial.groupBy("k").agg(*(F.sum(f"s{i}").alias(f"s{i}") for i in range(5)))
    mass = sum((F.col(f"s{i}") for i in range(1, 5)), F.col("s0"))
    return rounded(spv.exploded(merged.select("k", F.array(*(F.col(f"s{i}") / mass for i in range(5))).alias("q")), "q", "q"), "q")


# --- windows, order, sets ------------------------------------------------------------------


@query(_PARTS + "SELECT item_id, k::INT AS k, rank() OVER (PARTITION BY item_id ORDER BY c)::INT AS place FROM cost")
def rank_books(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = assign.divergences(fixture_spv(spark, sf_dir, "parts").select("item_id", "p"), fixed(3))
    return pairs.select("item_id", "k", F.rank().over(Window.partitionBy("item_id").orderBy("cost")).alias("place"))


@query(with_(spv_sql("events"), _CDF) + "SELECT item_id, round(hi, 6) AS upto FROM cdf")
def demand_cdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cumulative(fixture_demand(spark, sf_dir, "events")).select("item_id", r6("hi").alias("upto"))


@query(with_(requests()) + "SELECT event_id, coalesce(date_diff('microsecond', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts), -1)::BIGINT AS gap FROM req")
def request_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    stamps = request_log(spark, sf_dir).withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return stamps.select("event_id", F.coalesce(F.col("us") - F.lag("us").over(Window.partitionBy("user_id").orderBy("ts", "event_id")), F.lit(-1)).alias("gap"))


@query(with_(requests()) + "SELECT event_id, count(*) OVER (PARTITION BY item_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)::BIGINT AS recent FROM (SELECT event_id, item_id, date_trunc('second', ts) AS ts FROM req)")
def rolling_demand(spark: SparkSession, sf_dir: str) -> DataFrame:
    timed = request_log(spark, sf_dir).withColumn("s", F.unix_timestamp(F.col("ts").cast("timestamp")))
    return timed.select("event_id", F.count("*").over(Window.partitionBy("item_id").orderBy("s").rangeBetween(-86400, 0)).alias("recent"))


@query("WITH c AS (SELECT p_brand AS brand, p_partkey AS item_id, sum(l_quantity) AS w FROM part JOIN lineitem ON l_partkey = p_partkey GROUP BY 1, 2) SELECT item_id, ntile(4) OVER (PARTITION BY brand ORDER BY w DESC, item_id)::INT AS tile, round(percent_rank() OVER (PARTITION BY brand ORDER BY w DESC), 6) AS rnk FROM c")
def popularity_tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand"))
    weights = load(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("item_id")).agg(F.sum("l_quantity").alias("w"))
    window = Window.partitionBy("brand").orderBy(F.desc("w"))
    return parts.join(weights, "item_id").select("item_id", F.ntile(4).over(Window.partitionBy("brand").orderBy(F.desc("w"), "item_id")).alias("tile"), r6(F.percent_rank().over(window)).alias("rnk"))


@query(_PARTS + "SELECT item_id, round(c, 6) AS cost FROM best ORDER BY round(c, 6) DESC, item_id LIMIT 20")
def worst_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return choices(spark, sf_dir).select("item_id", r6("cost").alias("cost")).orderBy(F.desc("cost"), "item_id").limit(20)


@query(_PARTS + "SELECT k::INT AS k, item_id FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY round(f, 9) DESC, item_id) AS rn FROM best JOIN dem USING (item_id)) WHERE rn <= 3")
def top_items_per_book(spark: SparkSession, sf_dir: str) -> DataFrame:
    window = Window.partitionBy("k").orderBy(F.desc(F.round("f", 9)), "item_id")
    return choices(spark, sf_dir).withColumn("rn", F.row_number().over(window)).filter("rn <= 3").select("k", "item_id")


@query("SELECT p_partkey AS item_id, p_name FROM part ORDER BY p_partkey LIMIT 25 OFFSET 50")
def page_of_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_id"), "p_name").orderBy("item_id").offset(50).limit(25)


def _cohorts(spark: SparkSession, sf_dir: str) -> list[DataFrame]:
    """What the two cohorts of users asked for, by day: item, symbol and day."""
    log = request_log(spark, sf_dir).select("user_id", "item_id", "symbol", F.to_date("ts").cast("string").alias("day"))
    return [log.filter(F.col("user_id") % 2 == r).select("item_id", "symbol", "day") for r in (0, 1)]


_SETS = with_(requests())


@query(_SETS + "SELECT item_id, symbol, ts::DATE::VARCHAR AS day FROM req WHERE user_id % 2 = 0 INTERSECT SELECT item_id, symbol, ts::DATE::VARCHAR FROM req WHERE user_id % 2 = 1")
def common_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    one, two = _cohorts(spark, sf_dir)
    return one.intersect(two)


@query(_SETS + "SELECT item_id, symbol, ts::DATE::VARCHAR AS day FROM req WHERE user_id % 2 = 0 EXCEPT SELECT item_id, symbol, ts::DATE::VARCHAR FROM req WHERE user_id % 2 = 1")
def exclusive_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    one, two = _cohorts(spark, sf_dir)
    return one.subtract(two)


@query(_SETS + "SELECT channel::INT AS channel, item_id, count(*)::BIGINT AS c FROM (SELECT 1 AS channel, item_id FROM req WHERE user_id % 2 = 0 UNION ALL SELECT 2, item_id FROM req WHERE user_id % 2 = 1) GROUP BY 1, 2")
def channels_stacked(spark: SparkSession, sf_dir: str) -> DataFrame:
    log = request_log(spark, sf_dir)
    parts = [log.filter(F.col("user_id") % 2 == r).select("item_id", F.lit(r + 1).alias("channel")) for r in (0, 1)]
    return parts[0].unionByName(parts[1].select("channel", "item_id")).groupBy("channel", "item_id").agg(F.count("*").alias("c"))


# --- functions -----------------------------------------------------------------------------


@query(with_(spv_sql("customers")) + "SELECT item_id, count(*)::BIGINT AS present, round(max(p), 6) AS top FROM spv WHERE p > 0 GROUP BY item_id")
def spv_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sparse vectors as maps of the symbols that occur."""
    from prefbook.sources.tables import FIXTURES

    labels = F.array(*(F.lit(a) for a in FIXTURES["customers"].alphabet))
    sparse = fixture_spv(spark, sf_dir, "customers").select("item_id", F.map_filter(F.map_from_arrays(labels, "p"), lambda k, v: v > 0).alias("m"))
    return sparse.select("item_id", F.cardinality("m").cast("long").alias("present"), r6(F.array_max(F.map_values("m"))).alias("top"))


@query("SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS item_id FROM events")
def events_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long").getField("k").alias("item_id"))


@query(f"SELECT event_id, {u_sql(chr(39) + '7' + chr(39), 'event_id', '12')} AS u FROM events")
def hash_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").select("event_id", uniform_of(7, F.col("event_id"), 12).alias("u"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g'))::BIGINT AS chars, (length(html) - length(regexp_replace(html, '[0-9]', '', 'g')))::BIGINT AS digits FROM pages")
def spv_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages")
    return pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.char_length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("chars"), F.regexp_count("html", F.lit("[0-9]")).cast("long").alias("digits"))


@query("SELECT event_id, substr('00000' || bin(event_id % 16), -5) AS word FROM events")
def encode_symbols(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").select("event_id", F.lpad(F.bin(F.col("event_id") % 16), 5, "0").alias("word"))


@query("SELECT event_id, coalesce(try_cast(json_extract_string(props, '$.k') || CASE WHEN event_id % 7 = 0 THEN 'x' ELSE '' END AS BIGINT), -1) AS item_id FROM events")
def safe_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    dirty = F.concat(F.get_json_object("props", "$.k"), F.when(F.col("event_id") % 7 == 0, "x").otherwise(""))
    return load(spark, sf_dir, "events").select("event_id", F.coalesce(dirty.try_cast("long"), F.lit(-1)).alias("item_id"))

