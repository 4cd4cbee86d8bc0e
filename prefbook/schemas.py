"""Table contracts of the engine."""

from __future__ import annotations

from pyspark.sql import DataFrame

SYMBOL_COUNTS = "item_id long, symbol int, cnt long"
SPV = "item_id long, n_sym long, p array<double>"
DEMAND = "item_id long, f double"
JOINT = "i long, j long, f double"
#: Items of a design problem: symbol probabilities, entropy, and the weights of the three channels.
ITEMS = "item_id long, p array<double>, h double, w0 double, w1 double, w2 double"
BOOKS = "run_id int, pool int, k int, q array<double>"
BOOK_LENGTHS = "pool int, k int, symbol int, ideal_bits double, code_bits int, codeword string"
ASSIGNMENT = "run_id int, item_id long, channel int, pool int, k int, divergence double"
TRACE = "run_id int, iteration int, objective double, moved long, seconds double"
DESIGN_REPORT = "method string, n int, k int, k0 int, bits_per_request double, mismatch double, entropy_floor double, saving_pct double"

#: Symbols of an item in all of the experiments.
ITEM_LENGTH = 20
TOLERANCE = 1e-6


def check(df: DataFrame, schema: str, name: str) -> DataFrame:
    """``df`` with the columns of ``schema`` in its order and types; a missing column is an error."""
    wanted = [part.split(" ", 1) for part in schema.split(", ")]
    missing = [c for c, _ in wanted if c not in df.columns]
    if missing:
        raise ValueError(f"{name} lacks {', '.join(missing)}")
    return df.selectExpr(*(f"cast(`{c}` as {kind}) as `{c}`" for c, kind in wanted))
