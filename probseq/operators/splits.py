"""Increments of a database of sequences."""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def share(seq_id: Column | str = "seq_id", salt: str = "s") -> Column:
    """A number in [0, 1) from a sequence's id, equal in every engine with md5."""
    c = F.col(seq_id) if isinstance(seq_id, str) else seq_id
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt + "|"), c.cast("string"))), 1, 4), 16, 10).cast("long") / F.lit(65536.0)


def bounds(first: float = 0.5, n: int = 5, seed: int = 42) -> list[float]:
    """Upper ends of the shares of the initial part and of n increments of random sizes."""
    r = random.Random(seed)
    parts = [r.uniform(0.5, 1.5) for _ in range(n)]
    out, at = [first], first
    for p in parts:
        at += (1 - first) * p / sum(parts)
        out.append(at)
    out[-1] = 1.0
    return [round(x, 6) for x in out]


def growing_bounds(first: float, low: float = 0.5, high: float = 0.8, seed: int = 42) -> list[float]:
    """An initial part and as many increments of 50-80 % of its size as fill the rest."""
    r, out = random.Random(seed), [first]
    while out[-1] < 1 - 1e-9:
        out.append(min(1.0, out[-1] + first * r.uniform(low, high)))
    return [round(x, 6) for x in out]


def _part(x: Column, ends: list[float]) -> Column:
    c = F.when(x < ends[0], 0)
    for k, e in enumerate(ends[1:-1], 1):
        c = c.when(x < e, k)
    return c.otherwise(len(ends) - 1).cast("int")


def split_increments(occ: DataFrame, ends: list[float], by: str = "hash", time: str | None = None) -> DataFrame:
    """Adds batch_id: whole sequences, dealt by the hash of their id or by the share of their time in its range."""
    if by == "hash":
        return occ.withColumn("batch_id", _part(share(), ends))
    if by != "time" or time is None:
        raise ValueError("by is hash, or time with a column")
    t = F.unix_micros(F.col(time).cast("timestamp"))
    at = occ.agg(F.min(t).alias("_lo"), F.max(t).alias("_hi"))
    x = (t - F.col("_lo")) / (F.col("_hi") - F.col("_lo") + 1)
    return occ.crossJoin(F.broadcast(at)).withColumn("batch_id", _part(x, ends)).drop("_lo", "_hi")


def ranked(df: DataFrame, key: str, blocks: int = 4096) -> DataFrame:
    """Adds rank (from 0) by a unique whole number `key`, and total, without a task that holds all rows.

    The range of the key is cut into `blocks`; only their counts meet, and their running sums shift each block's ranks.
    """
    ends = df.agg(F.min(key).alias("_lo"), F.max(key).alias("_hi"), F.count(F.lit(1)).alias("total"))
    width = F.greatest(F.lit(1), F.ceil((F.col("_hi") - F.col("_lo") + 1) / blocks))
    cut = df.crossJoin(F.broadcast(ends)).withColumn("_block", F.floor((F.col(key) - F.col("_lo")) / width)).drop("_lo", "_hi")
    before = Window.orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    counts = cut.groupBy("_block").agg(F.count(F.lit(1)).alias("_n")).select("_block", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_shift"))
    own = F.row_number().over(Window.partitionBy("_block").orderBy(key)) - 1
    return cut.withColumn("_own", own).join(F.broadcast(counts), "_block").withColumn("rank", F.col("_own") + F.col("_shift")).drop("_block", "_own", "_shift")


def tile(rank: Column, total: Column, n: int) -> Column:
    """Which of n tiles a rank (from 0) falls in, from 1; the first tiles take what does not divide."""
    size, more = F.floor(total / n), total % n
    large = more * (size + 1)
    return (F.when(rank < large, F.floor(rank / (size + 1))).otherwise(more + F.floor((rank - large) / F.greatest(size, F.lit(1)))) + 1).cast("long")
