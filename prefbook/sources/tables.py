"""Base tables, and the items, symbols and demand that they stand for."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from prefbook.operators import demand, spv

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
EVENTS_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def requests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The request log: user_id, item_id (the event's property k), symbol (its type), ts."""
    return load(spark, sf_dir, "events").select("event_id", "user_id", F.get_json_object("props", "$.k").cast("long").alias("item_id"), F.col("event_type").alias("symbol"), "ts")


@dataclass(frozen=True)
class Fixture:
    """Rows (item_id, symbol, weight) of a base table; demand is the share of the weight."""

    table: str
    item: str
    symbol: Callable[[], Column]
    alphabet: tuple[str, ...]
    weight: str | None


#: Alphabets in alphabetical order.
FIXTURES = {
    "events": Fixture("events", "get_json_object(props, '$.k')", lambda: F.col("event_type"), ("click", "error", "purchase", "signup", "view"), None),
    "parts": Fixture("lineitem", "l_partkey", lambda: F.col("l_returnflag"), ("A", "N", "R"), "l_quantity"),
    "suppliers": Fixture("lineitem", "l_suppkey", lambda: F.concat("l_returnflag", "l_linestatus"), ("AF", "AO", "NF", "NO", "RF", "RO"), "l_quantity"),
    "customers": Fixture("orders", "o_custkey", lambda: F.col("o_orderpriority"), ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"), "o_totalprice"),
    "quarters": Fixture("orders", "o_custkey", lambda: F.quarter("o_orderdate").cast("string"), ("1", "2", "3", "4"), "o_totalprice"),
}


def symbols(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    fixture = FIXTURES[name]
    weight = F.col(fixture.weight).cast("double") if fixture.weight else F.lit(1.0)
    return load(spark, sf_dir, fixture.table).select(F.expr(fixture.item).cast("long").alias("item_id"), fixture.symbol().alias("symbol"), weight.alias("weight"))


def fixture_spv(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spv.from_symbols(symbols(spark, sf_dir, name), "item_id", "symbol", FIXTURES[name].alphabet)


def fixture_demand(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return demand.weighted(symbols(spark, sf_dir, name), "item_id", "weight")


def fixture_items(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """item_id, p, f from one scan and one shuffle: SPVs and demand are sums by item; the total reuses the exchange."""
    rows = spv.from_symbols(symbols(spark, sf_dir, name), "item_id", "symbol", FIXTURES[name].alphabet, weight="weight")
    total = rows.agg(F.sum("w").alias("total"))
    return rows.crossJoin(F.broadcast(total)).select("item_id", "p", (F.col("w") / F.col("total")).alias("f"))
