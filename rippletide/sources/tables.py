"""Readers and writers: the Parquet tables, edge lists, graphs and run logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    for name in names or TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read_edge_list(spark: SparkSession, path: str, sep: str = r"\s+", comment: str = "#") -> DataFrame:
    """White-space (or other) separated node pairs, comment lines skipped; further fields ignored."""
    lines = spark.read.text(path).where(~F.ltrim("value").startswith(comment) & (F.trim("value") != ""))
    parts = F.split(F.trim("value"), sep)
    return lines.select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))


def write_edge_list(edges: DataFrame, path: str, sep: str = "\t") -> None:
    edges.select(F.concat_ws(sep, "u", "v").alias("value")).write.mode("overwrite").text(path)


def read_edges_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("u long, v long, p double, w double, phi double").json(path)


def write_graph(nodes: DataFrame, edges: DataFrame, path: str) -> None:
    nodes.write.mode("overwrite").parquet(f"{path}/nodes")
    edges.repartition("v").sortWithinPartitions("v", "u").write.mode("overwrite").parquet(f"{path}/edges")


def read_graph(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    return spark.read.parquet(f"{path}/nodes"), spark.read.parquet(f"{path}/edges")


def save_bucketed(edges: DataFrame, name: str, buckets: int, by: str = "v") -> None:
    """Managed table bucketed by one endpoint, so that joins on it need no exchange."""
    edges.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def append_run_log(rows: DataFrame, path: str) -> None:
    rows.write.mode("append").parquet(path)
