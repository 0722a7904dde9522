"""Registry that pairs each query with its DuckDB oracle."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


# Tables whose rows are long texts: work grows with their length, so a table in few files is dealt out first.
TEXTS = {"documents", "pages"}


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One of the given tables; columns are pruned later by the optimizer.

    A text table that would be read by fewer tasks than there are cores is dealt
    out over them; larger inputs are read as they are, without an exchange.
    """
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return dealt(df) if table in TEXTS else df


def dealt(df: DataFrame) -> DataFrame:
    """``df`` over as many tasks as there are cores, if it would be read by fewer."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df._jdf.queryExecution().toRdd().getNumPartitions() < cores else df


class Tables:
    """Attribute access to the tables of one folder: ``t.orders``."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        return load(self.spark, self.sf_dir, name)


def _call(fn, spark, sf_dir):
    return fn(Tables(spark, sf_dir))


def query(name: str, sql: str | None = None):
    """Register ``fn(tables) -> DataFrame`` under a name, with its oracle if SQL can say it."""

    def wrap(fn):
        QUERIES[name] = partial(_call, fn)
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return wrap
