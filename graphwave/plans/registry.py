"""The registry that query modules fill: name to builder, and name to the DuckDB text of the same result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..operators.directory import build_needs
from ..operators.layout import GraphLayout, layout
from ..operators.traverse import Run, bfs
from ..operators.exchange import ledger
from .lineage import cut, memo

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def register(name: str, build: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"{name} is registered twice")
    QUERIES[name] = build
    if sql is not None:
        ORACLES[name] = sql


def graph(spark: SparkSession, sf_dir: str, name: str, p: int | None = None) -> GraphLayout:
    """A graph's layout, written once per application."""
    return memo(spark, ("layout", sf_dir, name, p), lambda: layout(spark, sf_dir, name, p))


def directory(spark: SparkSession, sf_dir: str, name: str, p: int | None = None) -> DataFrame:
    return memo(spark, ("needs", sf_dir, name, p), lambda: cut(build_needs(graph(spark, sf_dir, name, p)).repartition("owner_block")))


def run(spark: SparkSession, sf_dir: str, name: str, method: str = "relational", p: int | None = None) -> Run:
    def make():
        g = graph(spark, sf_dir, name, p)
        sieved = method.endswith("sieved")
        return bfs(g, method=method, needs=directory(spark, sf_dir, name, p) if sieved else None)

    return memo(spark, ("run", sf_dir, name, method, p), make)


def tree(spark: SparkSession, sf_dir: str, name: str, p: int | None = None) -> DataFrame:
    return run(spark, sf_dir, name, "relational", p).tree


def book(spark: SparkSession, sf_dir: str, name: str, codec: str, sieved: bool, p: int | None = None) -> DataFrame:
    """The set-lane ledger of a search."""

    def make():
        return cut(ledger(graph(spark, sf_dir, name, p), tree(spark, sf_dir, name, p), codec, directory(spark, sf_dir, name, p) if sieved else None))

    return memo(spark, ("book", sf_dir, name, codec, sieved, p), make)
