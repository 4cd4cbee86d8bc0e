"""What the operators need of the session: shared storage, tables, process caches."""

from __future__ import annotations

import sys
import tempfile
import types
from collections.abc import Callable
from typing import Any

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType


def column(name: str) -> Column:
    """The column of exactly this name, whatever characters it has."""
    return F.col("`" + name.replace("`", "``") + "`")


def fresh(taken: list[str], *stems: str) -> list[str]:
    """Names that begin with the stems and that no column has, in either case of letters."""
    used, out = {c.lower() for c in taken}, []
    for stem in stems:
        name, k = stem, 0
        while name.lower() in used:
            name, k = f"{stem}_{k}", k + 1
        used.add(name.lower())
        out.append(name)
    return out


def settle(df: DataFrame) -> DataFrame:
    """Written to the shared checkpoint folder and read back: a lost executor costs no recomputation, and lineage ends.

    The folder is the session's ``spark.checkpoint.dir``. Without one, only a session whose executors are in the
    driver's process gets a folder of its own; on a cluster that would be lost with its machine, and is an error.
    """
    spark = df.sparkSession
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not context._jsc.sc().isLocal():
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="prefbook-checkpoints-")
        context.setCheckpointDir(folder)
    return df.checkpoint(eager=True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes of an Arrow batch; each task holds a few of them in the JVM and in Python, beyond the JVM's heap.
BATCH_BYTES = 4 << 20
_BATCH_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def fields(df: DataFrame, columns: list[str], *more: tuple[str, str]) -> StructType:
    """The schema of some columns of ``df`` and of further (name, type) ones; names may have any characters."""
    kinds = {f.name: f for f in df.schema.fields}
    return StructType([*(kinds[c] for c in columns), *(StructField(name, StructType.fromDDL(f"x {kind}")["x"].dataType) for name, kind in more)])


def _awkward(names: list[str]) -> bool:
    return any(c in name for name in names for c in ".`")


def arrow_map(df: DataFrame, function: Callable, schema: Any) -> DataFrame:
    """``df.mapInArrow`` in batches of bounded bytes; a row is never cut. The setting can be changed at run time, and
    counts when the query runs, so it stays. Names that Spark can't pass are replaced on the way in and out."""
    given, wanted = df.columns, schema.names if isinstance(schema, StructType) else []
    if _awkward([*given, *wanted]):
        plain = function
        inner = [f"c{i}" for i in range(len(wanted))]

        def function(batches):
            for out in plain(pa.RecordBatch.from_arrays(b.columns, names=given) for b in batches):
                yield pa.RecordBatch.from_arrays(out.columns, names=inner) if inner else out

        df = df.toDF(*(f"c{i}" for i in range(len(given))))
        if wanted:
            renamed = StructType([StructField(n, f.dataType) for n, f in zip(inner, schema.fields)])
            return _mapped(df, function, renamed).toDF(*wanted)
    return _mapped(df, function, schema)


def _mapped(df: DataFrame, function: Callable, schema: Any) -> DataFrame:
    conf = df.sparkSession.conf
    now = conf.get(_BATCH_SETTING)
    if now != str(BATCH_BYTES):
        number = int(now.removesuffix("b")) if now.removesuffix("b").isdigit() else 0
        if not 0 < number < BATCH_BYTES:
            conf.set(_BATCH_SETTING, str(BATCH_BYTES))
    return df.mapInArrow(function, schema)


def process_cache(key: Any, make: Callable[[], Any]) -> Any:
    """One value for each key in a Python worker, kept between tasks."""
    module = sys.modules.setdefault("_prefbook_process_cache", types.ModuleType("_prefbook_process_cache"))
    kept = module.__dict__.setdefault("kept", {})
    if key not in kept:
        kept[key] = make()
    return kept[key]
