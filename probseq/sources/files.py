"""Occurrences from files of common formats, with the schema given and never guessed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probseq.sources.text import parse_lines

SCHEMA = "seq_id long, pos int, item string, p double"
FORMATS = ("parquet", "orc", "json", "csv", "text")


def read_occurrences(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """(seq_id, pos, item, p) of Parquet, ORC, JSON lines, CSV with a header, or the sequence text format.

    Malformed CSV and JSON rows raise instead of turning into nulls. The text format has no ids: its sequences are numbered anew.
    """
    if kind not in FORMATS:
        raise ValueError(f"kind must be one of {', '.join(FORMATS)}, not {kind!r}")
    if kind == "text":
        return parse_lines(spark.read.text(path).select(F.monotonically_increasing_id().alias("seq_id"), "value"))
    reader = spark.read.schema(SCHEMA)
    if kind == "csv":
        reader = reader.option("header", True)
    if kind in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return reader.format(kind).load(path)


def write_occurrences(occ: DataFrame, path: str, kind: str = "parquet") -> None:
    """The same formats as `read_occurrences`."""
    from probseq.sources import sinks

    rows = occ.selectExpr("cast(seq_id as long) seq_id", "cast(pos as int) pos", "item", "p")
    if kind not in FORMATS:
        raise ValueError(f"kind must be one of {', '.join(FORMATS)}, not {kind!r}")
    if kind == "text":
        sinks.write_sequence_text(rows, path)
    elif kind == "csv":
        sinks.write_csv(rows, path)
    elif kind == "json":
        sinks.write_json(rows, path)
    else:
        rows.write.mode("overwrite").format(kind).save(path)
