"""The public text format of sequence sets: items separated by blanks, -1 ends an event, -2 ends a sequence.

An item may carry a probability as `item:p`; without one it is certain.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def parse_lines(lines: DataFrame, seq_id: str = "seq_id", text: str = "value") -> DataFrame:
    """(seq_id, pos, item, p) of lines with one sequence each."""
    body = F.split_part(text, F.lit("-2"), F.lit(1))
    events = F.filter(F.transform(F.split(body, r"(?<![^ ])-1(?![^ ])"), lambda e: F.trim(e)), lambda e: e != "")
    at = lines.select(F.col(seq_id).cast("long").alias("seq_id"), F.posexplode(events).alias("k", "e"))
    each = at.select("seq_id", (F.col("k") + 1).alias("pos"), F.explode(F.split("e", " +")).alias("x"))
    p = F.when(F.instr("x", ":") > 0, F.element_at(F.split("x", ":"), -1).cast("double")).otherwise(F.lit(1.0))
    return each.select("seq_id", "pos", F.split_part("x", F.lit(":"), F.lit(1)).alias("item"), p.alias("p"))


def read_sequence_text(spark: SparkSession, path: str) -> DataFrame:
    """Sequences of one or more files; ids count lines within a file and are kept apart by a hash of the file's name."""
    lines = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("f"), F.monotonically_increasing_id().alias("m")).where(F.trim("value") != "")
    return parse_lines(lines.withColumn("seq_id", F.xxhash64("f", "m")))


def to_lines(occ: DataFrame) -> DataFrame:
    """(seq_id, value) in the same format, with probabilities."""
    part = F.concat("item", F.lit(":"), F.col("p").cast("string"))
    per = occ.groupBy("seq_id", "pos").agg(F.array_join(F.array_sort(F.collect_list(part)), " ").alias("e"))
    rows = per.groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct("pos", "e"))).alias("x"))
    return rows.select("seq_id", F.concat(F.array_join(F.transform("x", lambda x: x["e"]), " -1 "), F.lit(" -1 -2")).alias("value"))


class _Span(InputPartition):
    def __init__(self, path: str, start: int, stop: int):
        self.path, self.start, self.stop = path, start, stop


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]
        self.size = int(options.get("split_bytes", 64 << 20))

    def partitions(self) -> list[InputPartition]:
        import os

        names = sorted(os.path.join(self.path, n) for n in os.listdir(self.path)) if os.path.isdir(self.path) else [self.path]
        return [_Span(n, a, min(a + self.size, s)) for n in names if (s := os.path.getsize(n)) for a in range(0, s, self.size)]

    def read(self, partition: _Span) -> Iterator[tuple]:
        """Lines that begin within the span; the id is the place of the line in its file."""
        with open(partition.path, "rb") as f:
            f.seek(partition.start)
            if partition.start:
                f.seek(partition.start - 1)
                f.readline()
            while (at := f.tell()) < partition.stop and (line := f.readline()):
                pos = 1
                for event in line.decode().split("-2")[0].split(" -1"):
                    items = event.split()
                    for x in items:
                        name, _, p = x.partition(":")
                        yield at, pos, name, float(p) if p else 1.0
                    pos += bool(items)


class SequenceTextSource(DataSource):
    """format("sequence_text"): splittable reader of the text format for local or mounted files."""

    @classmethod
    def name(cls) -> str:
        return "sequence_text"

    def schema(self) -> str:
        return "seq_id long, pos int, item string, p double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))
