"""All named queries of the library and the DuckDB text of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .plans import cost_queries, relational_queries, search_queries  # noqa: F401  they fill the registry
from .plans.registry import ORACLES, QUERIES, tree
from .streaming import queries as stream_queries  # noqa: F401

SMALL = "/root/testdata/sf0.001"


def entry(spark: SparkSession, sf_dir: str = SMALL) -> DataFrame:
    return tree(spark, sf_dir, "order_part")


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
