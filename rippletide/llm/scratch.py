"""Intermediate tables in the folder that driver and executors share."""

from pyspark.sql import DataFrame

from rippletide.plans import storage
from rippletide.plans.storage import discard, fresh_path, holding, shared_dir

__all__ = ["discard", "fresh_path", "holding", "shared_dir", "stored"]
#: While a table is written, what a Python task gets at a time is bounded in bytes, not in rows.
BATCH = {"spark.sql.execution.arrow.maxBytesPerBatch": "4m"}


def stored(df: DataFrame, label: str) -> DataFrame:
    with holding(df.sparkSession, BATCH):
        return storage.stored(df, label)
