"""Loading the given tables with column pruning, and edge lists in other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGE_SCHEMA = T.StructType([T.StructField("u", T.LongType()), T.StructField("v", T.LongType())])


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def size(spark: SparkSession, sf_dir: str, name: str) -> int:
    """Rows of a table, from Parquet footers."""
    return load(spark, sf_dir, name).count()


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType = EDGE_SCHEMA, separator: str = ",") -> DataFrame:
    """An edge list in parquet, orc, csv, tsv, json or text (u and v between blanks), by a given schema."""
    if fmt in ("csv", "tsv"):
        return spark.read.schema(schema).option("sep", "\t" if fmt == "tsv" else separator).csv(path)
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).where(~F.col("value").startswith("#")).select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
    return spark.read.schema(schema).format(fmt).load(path)


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    if fmt == "text":
        edges.select(F.concat_ws(" ", F.col("u").cast("string"), F.col("v").cast("string"))).write.mode("overwrite").text(path)
    elif fmt == "tsv":
        edges.write.mode("overwrite").option("sep", "\t").csv(path)
    else:
        edges.write.mode("overwrite").format(fmt).save(path)


def save_run(run, path: str, run_id: str, method: str) -> None:
    """Writes a search: its tree by level, its ledger and its seconds by phase, each as a table that further runs are added to."""
    row = lambda df: df.withColumns({"run_id": F.lit(run_id), "method": F.lit(method)})
    row(run.tree).write.mode("append").partitionBy("run_id", "level").parquet(f"{path}/trees")
    if run.ledger is not None:
        row(run.ledger).write.mode("append").partitionBy("run_id").parquet(f"{path}/ledgers")
    if run.seconds:
        run.profile(run_id, method).write.mode("append").partitionBy("run_id").parquet(f"{path}/profiles")


def load_run(spark: SparkSession, path: str, run_id: str) -> DataFrame:
    """(vid, level, parent) of a written search; a filter on level reads only its files."""
    return spark.read.parquet(f"{path}/trees").where(F.col("run_id") == run_id).select("vid", F.col("level").cast("long").alias("level"), "parent")
