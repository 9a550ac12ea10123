"""Where matches go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_matches(matches: DataFrame, path: str, batch_id: int | None = None) -> None:
    """Parquet; with a batch id into that batch's folder, which a replay writes over."""
    target = path if batch_id is None else f"{path}/batch_id={batch_id}"
    matches.write.mode("overwrite").parquet(target)


def read_matches(spark, path: str) -> DataFrame:
    """All batches, with ``batch_id`` as a column that prunes folders."""
    return spark.read.option("basePath", path).parquet(path)


def run_only(matches: DataFrame) -> None:
    """Computes everything and keeps nothing, for timing."""
    matches.write.format("noop").mode("overwrite").save()
