"""File sources and sinks in the shared store: round trips, training samples as JSON lines, rounds as partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame

from tablemill.streaming.windows import scratch


def round_trip(df: DataFrame, fmt: str, **options) -> DataFrame:
    """Write and read back in another format, with the schema known."""
    path = scratch(df.sparkSession, f"io-{fmt}")
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).schema(df.schema).options(**options).load(path)


def sample_lines(samples: DataFrame) -> DataFrame:
    """Samples as JSON lines, read back as text: one line a sample."""
    path = scratch(samples.sparkSession, "samples")
    samples.write.option("compression", "gzip").json(path)
    return samples.sparkSession.read.text(path)


def save_round(samples: DataFrame, path: str) -> None:
    """Write a refinement round; only the rounds present in ``samples`` are replaced."""
    samples.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("round").parquet(path)
