"""Where results go: versioned Parquet, buckets by sequence, text exports."""

from __future__ import annotations

from pyspark.sql import DataFrame

from probseq.sources.text import to_lines


def write_versions(df: DataFrame, path: str, by: str = "batch_id") -> None:
    """Parquet partitioned by a version column; only the versions in `df` are replaced."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)


def write_bucketed(occ: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed and sorted by sequence: level joins on seq_id then need no exchange."""
    occ.write.mode("overwrite").bucketBy(buckets, "seq_id").sortBy("seq_id", "pos").saveAsTable(table)


def write_csv(result: DataFrame, path: str) -> None:
    result.write.mode("overwrite").option("header", True).csv(path)


def write_json(result: DataFrame, path: str) -> None:
    result.write.mode("overwrite").json(path)


def write_sequence_text(occ: DataFrame, path: str) -> None:
    to_lines(occ).select("value").write.mode("overwrite").text(path)
