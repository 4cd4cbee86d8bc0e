"""Named queries (spark, sf_dir) -> DataFrame, and DuckDB SQL with the same rows."""

from prefbook.queries import designs, experiments, measures, models, relational
from prefbook.queries.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "designs", "experiments", "measures", "models", "relational"]
