"""The information measures as SQL functions that Catalyst inlines, and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

_TERM = "CASE WHEN {p} <= 0 THEN 0D WHEN {q} <= 0 THEN double('infinity') ELSE -{p} * log2({q}) END"
#: Spelled out where the arguments are lambda variables, which SQL functions can't take.
CROSS = "aggregate(zip_with({p}, {q}, (x, y) -> " + _TERM.format(p="x", q="y") + "), 0D, (s, x) -> s + x)"

DEFINITIONS = {
    "entropy_bits": f"(p ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(transform(p, x -> {_TERM.format(p='x', q='x')}), 0D, (s, x) -> s + x)",
    "cross_bits": f"(p ARRAY<DOUBLE>, q ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {CROSS.format(p='p', q='q')}",
    "kl_bits": "(p ARRAY<DOUBLE>, q ARRAY<DOUBLE>) RETURNS DOUBLE RETURN cross_bits(p, q) - entropy_bits(p)",
    "nearest_book": f"(p ARRAY<DOUBLE>, books ARRAY<ARRAY<DOUBLE>>) RETURNS INT RETURN array_min(transform(books, (b, k) -> struct({CROSS.format(p='p', q='b')} AS c, k AS k))).k",
}


def register(spark: SparkSession) -> None:
    for name, rest in DEFINITIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{rest}")


@udtf(returnType="symbol int, bits int, codeword string")
class CodeTable:
    """Canonical prefix code for the ideal lengths of a codebook: one row per symbol with a positive share."""

    def eval(self, q: list):
        from prefbook.operators.codec import integer_code

        for symbol, (bits, word) in integer_code([float(x) for x in q]).items():
            yield symbol, bits, word


@udtf(returnType="cell long, p array<double>")
class SimplexPoints:
    """Centres of the cells of a triangular lattice; the built-in generator does the same without Python."""

    def eval(self, grid: int):
        for a in range(grid):
            for b in range(grid - a):
                yield a * grid + b, [(a + 1 / 3) / grid, (b + 1 / 3) / grid, 1 - (a + b + 2 / 3) / grid]
                if a + b < grid - 1:
                    yield grid * grid + a * grid + b, [(a + 2 / 3) / grid, (b + 2 / 3) / grid, 1 - (a + b + 4 / 3) / grid]


def register_tables(spark: SparkSession) -> None:
    spark.udtf.register("code_table", CodeTable)
    spark.udtf.register("simplex_points", SimplexPoints)
