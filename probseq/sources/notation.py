"""Uncertain sequences written as `(a:0.9, c:0.6)(b:0.3)`."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def parse(text: Column | str) -> Column:
    """array<array<struct<item, p>>>; an item without a number has probability 1."""
    events = F.regexp_extract_all(text, F.lit(r"\(([^)]*)\)"), F.lit(1))
    part = lambda x: F.struct(F.trim(F.split_part(x, F.lit(":"), F.lit(1))).alias("item"), F.coalesce(F.try_to_number(F.nullif(F.trim(F.split_part(x, F.lit(":"), F.lit(2))), F.lit("")), F.lit("9.999999999")).cast("double"), F.lit(1.0)).alias("p"))
    return F.transform(events, lambda e: F.transform(F.filter(F.split(e, ","), lambda x: F.trim(x) != ""), part))


def occurrences(rows: DataFrame, seq_id: str = "seq_id", text: str = "sequence") -> DataFrame:
    """(seq_id, pos, item, p) of rows with a sequence in this notation; positions count from 1."""
    at = rows.select(F.col(seq_id).cast("long").alias("seq_id"), F.posexplode(parse(text)).alias("_k", "_e"))
    return at.select("seq_id", (F.col("_k") + 1).alias("pos"), F.explode("_e").alias("_o")).select("seq_id", "pos", "_o.item", "_o.p")


def render(occ: DataFrame) -> DataFrame:
    """(seq_id, sequence) in this notation."""
    part = F.concat("item", F.lit(":"), F.col("p").cast("string"))
    per = occ.groupBy("seq_id", "pos").agg(F.concat(F.lit("("), F.array_join(F.array_sort(F.collect_list(part)), ", "), F.lit(")")).alias("e"))
    return per.groupBy("seq_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "e"))), lambda x: x["e"]), "").alias("sequence"))
