"""Probabilities and weights for data that have none."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MEAN, P_SD, W_SD = 0.5, 0.25, 0.125


def deviate(key: Column) -> Column:
    """A near-normal deviate from a text: the first 12 bytes of its md5 summed, centred and scaled.

    The sum of 12 uniform bytes has mean 1530 and deviation 255.998; any engine with md5 gets the same number.
    """
    h = F.md5(key)
    six = [F.conv(F.substring(h, k, 12), 16, 10).cast("long") for k in (1, 13)]  # bytes as one number, as each conversion costs
    total = sum((F.shiftright(x, 8 * k).bitwiseAND(F.lit(255)) for x in six for k in range(6)), F.lit(0))
    return (total - 1530) / F.lit(255.998)


def _clipped(z: Column, sd: float) -> Column:
    return F.round(F.least(F.lit(1.0), F.greatest(F.lit(0.01), F.lit(MEAN) + F.lit(sd) * z)), 2)


def probability() -> Column:
    """Of seq_id, pos and item: near N(0.5, 0.25), clipped to [0.01, 1].

    Costly right on top of an aggregate, whose results share no subexpressions: there every use of the hash makes it anew.
    """
    key = F.concat_ws("|", F.lit("p"), F.col("seq_id").cast("string"), F.col("pos").cast("string"), F.col("item"))
    return _clipped(deviate(key), P_SD)


def normal_probability(occ: DataFrame) -> DataFrame:
    """(seq_id, pos, item, p) with p near N(0.5, 0.25), clipped to [0.01, 1]."""
    return occ.select("seq_id", "pos", "item", probability().alias("p"))


def normal_weights(items: DataFrame) -> DataFrame:
    """(item, weight) with weights near N(0.5, 0.125), clipped to [0.01, 1]."""
    return items.select("item").distinct().select("item", _clipped(deviate(F.concat(F.lit("w|"), "item")), W_SD).alias("weight"))


def random_probability(occ: DataFrame, seed: int = 42) -> DataFrame:
    """True normal deviates by Box-Muller on row hashes: repeatable, whatever the partitioning."""
    bits = lambda salt: (F.pmod(F.xxhash64("seq_id", "pos", "item", F.lit(seed), F.lit(salt)), F.lit(1 << 52)) + 1) / F.lit(float(1 << 52))
    z = F.sqrt(-2 * F.log(bits(1))) * F.cos(2 * 3.141592653589793 * bits(2))
    return occ.select("seq_id", "pos", "item", _clipped(z, P_SD).alias("p"))


def certain(occ: DataFrame) -> DataFrame:
    """Precise data: every probability is 1."""
    return occ.select("seq_id", "pos", "item", F.lit(1.0).alias("p"))


def price_weights(part: DataFrame, item: Column) -> DataFrame:
    """(item, weight): mean retail price of an item over the largest such mean."""
    mean = part.groupBy(item.alias("item")).agg(F.avg("p_retailprice").alias("m"))
    top = mean.agg(F.max("m").alias("top"))
    return mean.crossJoin(F.broadcast(top)).select("item", (F.col("m") / F.col("top")).alias("weight"))


def quantity_probability(rows: DataFrame, quantity: str, most: float) -> DataFrame:
    """(seq_id, pos, item, p): the larger a quantity, up to `most`, the less certain; p in [0.01, 1]."""
    p = F.lit(0.05) + 0.9 * (1 - F.col(quantity) / most)
    return rows.select("seq_id", "pos", "item", F.least(F.lit(1.0), F.greatest(F.lit(0.01), p)).alias("p"))
