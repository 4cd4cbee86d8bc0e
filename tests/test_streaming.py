"""Streams give what batches give."""

import shutil

import numpy as np
import pytest
from pyspark.sql import functions as F

from prefbook.operators.measures import expected_bits
from prefbook.operators.simplex import portable_books
from prefbook.sources.tables import fixture_spv
from prefbook.streaming import requests as stream


@pytest.fixture(scope="module")
def split(spark, small, tmp_path_factory):
    """The events in three files, in the order of time; the first one is there twice."""
    folder = tmp_path_factory.mktemp("events")
    events = spark.read.parquet(f"{small}/events.parquet").toPandas().sort_values("ts")
    for i, part in enumerate(np.array_split(np.arange(len(events)), 3)):
        out = f"{folder}/raw{i}"
        spark.createDataFrame(events.iloc[part]).select(F.col("event_id"), F.col("ts").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value", "props").coalesce(1).write.parquet(out)
        import glob

        shutil.copy(glob.glob(f"{out}/part-*.parquet")[0], f"{folder}/events{i}.parquet")
        shutil.rmtree(out)
    return str(folder)


@pytest.fixture
def batch(spark, small):
    return stream.as_requests(spark.read.parquet(f"{small}/events.parquet"))


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_windows(spark, split, batch):
    for name, args in (("tumbling", ("1 day",)), ("sliding", ("7 days", "1 day"))):
        got = stream.drain(stream.windowed_demand(stream.read(spark, split, per_trigger=1), *args), "complete", name)
        assert rows(got) == rows(stream.windowed_demand(batch, *args))


def test_append_leaves_open_windows(spark, split, batch):
    got = stream.drain(stream.windowed_demand(stream.read(spark, split, per_trigger=1)), "append", "closed")
    every = stream.windowed_demand(batch)
    assert 0 < got.count() < every.count() and set(rows(got)) <= set(rows(every))


def test_sessions(spark, split, batch):
    got = stream.drain(stream.sessions(stream.read(spark, split, per_trigger=1)), "complete", "bursts")
    assert rows(got) == rows(stream.sessions(batch))


def test_deduplication(spark, split, batch, tmp_path):
    for i in range(3):
        shutil.copy(f"{split}/events{i}.parquet", f"{tmp_path}/events{i}.parquet")
        shutil.copy(f"{split}/events{i}.parquet", f"{tmp_path}/events{i}again.parquet")
    got = stream.drain(stream.deduplicated(stream.read(spark, str(tmp_path), per_trigger=2)), "append", "once")
    assert got.count() == batch.count() == got.select("event_id").distinct().count()


def test_online_cost(spark, split, small, batch):
    spv, q = fixture_spv(spark, small, "events"), portable_books(5, 3)
    got = stream.drain(stream.online_cost(stream.read(spark, split, per_trigger=1), spv, q), "complete", "cost")
    want = {r.symbol: r for r in stream.online_cost(batch, spv, q).collect()}
    for r in got.collect():
        assert r.c == want[r.symbol].c and r.bits == pytest.approx(want[r.symbol].bits)


def test_joint(spark, split, batch):
    got = stream.drain(stream.joint_requests(stream.read(spark, split, per_trigger=1)), "append", "pairs")
    assert rows(got) == rows(stream.joint_requests(batch))


def test_user_state(spark, split, batch):
    got = stream.drain(stream.user_demand(stream.read(spark, split, per_trigger=1)), "update", "users")
    last = got.groupBy("user_id").agg(F.max("requests").alias("n"))
    assert rows(last) == rows(batch.groupBy("user_id").agg(F.count("*").alias("n")))


def test_redesign(spark, split, small, batch):
    spv = fixture_spv(spark, small, "events").persist()
    q = 0.9 * portable_books(5, 3) + 0.02
    follow = stream.Redesign(spv, q)
    stream.each_batch(stream.read(spark, split, per_trigger=1), follow)
    assert len(follow.done) == 3 and follow.t.sum() == pytest.approx(batch.count())
    before = follow.q.copy()
    follow(batch, 0)
    assert np.array_equal(before, follow.q)
    items = batch.groupBy("item_id").agg(F.count("*").cast("double").alias("f")).join(spv, "item_id")
    assert expected_bits(items, follow.q).first()[0] <= expected_bits(items, q).first()[0]
    assert np.allclose(follow.q.sum(axis=1), 1.0)
