"""Materialised steps of iterative plans, in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []
#: Largest number of rows that a side may have to be broadcast after a count.
BROADCAST_ROWS = 200_000


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session. Only a local master (tests) may do without it."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        if not _OWN:
            _OWN.append("file://" + tempfile.mkdtemp(prefix="rippletide-"))
        root = _OWN[0]
    return root.rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/rippletide/{label}-{uuid.uuid4().hex}"


@contextmanager
def holding(spark: SparkSession, settings: dict[str, str]) -> Iterator[None]:
    """Runtime settings for what runs inside; afterwards they are as they were."""
    before = {k: spark.conf.get(k, None) for k in settings}
    for k, v in settings.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def stored(df: DataFrame, label: str = "step") -> DataFrame:
    """Written as Parquet and read back: lineage ends here and lost executors re-read. The write's own
    shuffle files go once it is done."""
    spark = df.sparkSession
    path, schema = fresh_path(spark, label), df.schema
    with holding(spark, {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}):
        df.write.parquet(path)
    out = spark.read.schema(schema).parquet(path)
    out.stored_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete stored tables that nothing reads any more, because all that came from them is stored."""
    for df in tables:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(df.stored_at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def stored_with_count(df: DataFrame, label: str = "step") -> tuple[DataFrame, int]:
    out = stored(df, label)
    return out, out.count()


def small(df: DataFrame, rows: int) -> DataFrame:
    """Broadcast hint where the counted ``rows`` are within bounds; otherwise the frame as it is."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def by_target(edges: DataFrame, partitions: int | None = None) -> DataFrame:
    """Arcs hash-partitioned by head ``v`` and stored: rounds that join on v move only node state."""
    laid = edges.repartition(partitions, "v") if partitions else edges.repartition("v")
    return stored(laid, "arcs")
