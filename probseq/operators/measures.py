"""Measures and thresholds as DataFrame expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from probseq.config import SLACK
from probseq.functions import patterns as P
from probseq.operators.encode import dictionary, suffix_max


def database_stats(occ: DataFrame, weights: DataFrame | None = None, freq: str = "occurrences") -> DataFrame:
    """One row: n_seq, wam (frequency-weighted mean of item weights), w_max."""
    f = "occ" if freq == "occurrences" else "seqs"
    d = dictionary(occ, weights)
    mean = d.agg((F.sum(F.col("weight") * F.col(f)) / F.sum(f)).alias("wam"), F.max("weight").alias("w_max"))
    n = occ.select("seq_id").distinct().agg(F.count(F.lit(1)).alias("n_seq"))
    return n.crossJoin(mean)  # one row each


def weight_mean(dict_: DataFrame, freq: str = "occurrences") -> DataFrame:
    f = "occ" if freq == "occurrences" else "seqs"
    return dict_.agg((F.sum(F.col("weight") * F.col(f)) / F.sum(f)).alias("wam"))


def global_threshold(n, wam, min_sup: float, wgt_fct: float = 1.0):
    """Works on numbers and on columns."""
    return min_sup * n * wam * wgt_fct


def buffer_threshold(min_wes, mu: float):
    return mu * min_wes


def local_threshold(delta_n, wam, min_sup: float, mu: float, gamma: float, wgt_fct: float = 1.0):
    return gamma * mu * min_sup * delta_n * wam * wgt_fct


def meets(value: Column, threshold: Column | float) -> Column:
    """`value` reaches `threshold`, but for the last digits of a sum."""
    return value >= threshold * (1 - SLACK)


def seq_weight(patterns: DataFrame, weights: DataFrame | None) -> DataFrame:
    """(pattern, seq_weight): the mean weight of a pattern's items."""
    if weights is None:
        return patterns.select("pattern", F.lit(1.0).alias("seq_weight"))
    each = patterns.select("pattern", F.posexplode(F.flatten(P.events("pattern"))).alias("_k", "item"))
    return each.join(weights.select("item", "weight"), "item", "left").groupBy("pattern").agg(F.avg(F.coalesce("weight", F.lit(1.0))).alias("seq_weight"))


def weighted_expected_support(es: Column, weight: Column) -> Column:
    return es * weight


def pair_stats(occ: DataFrame) -> DataFrame:
    """Statistics of all extensions of one-item prefixes: (prefix, kind, item, max, sum, count) of suffix maxima.

    Only the earliest end of a prefix counts for s-extensions; i-extensions use every event with the prefix.
    """
    o = suffix_max(occ).select("seq_id", "pos", "item", "p_sfx")
    first = o.groupBy("seq_id", F.col("item").alias("prefix")).agg(F.min("pos").alias("e0"))
    s = first.join(o, "seq_id").where(F.col("pos") > F.col("e0")).groupBy("prefix", F.lit("S").alias("kind"), "item", "seq_id").agg(F.max("p_sfx").alias("best"))
    left = o.select("seq_id", "pos", F.col("item").alias("prefix"))
    i = left.join(o, ["seq_id", "pos"]).where(F.col("item") > F.col("prefix")).groupBy("prefix", F.lit("I").alias("kind"), "item", "seq_id").agg(F.max("p_sfx").alias("best"))
    return s.unionByName(i).groupBy("prefix", "kind", "item").agg(F.max("best").alias("mx"), F.sum("best").alias("sm"), F.count(F.lit(1)).alias("ct"))


def item_stats(occ: DataFrame) -> DataFrame:
    """(item, mx, sm, ct) of each item's best probability per sequence."""
    per = occ.groupBy("item", "seq_id").agg(F.max("p").alias("best"))
    return per.groupBy("item").agg(F.max("best").alias("mx"), F.sum("best").alias("sm"), F.count(F.lit(1)).alias("ct"))


def pair_caps(occ: DataFrame) -> DataFrame:
    """(pattern, max_pr, es_cap, es_cap_loose, support_rows) of all two-item patterns."""
    one = item_stats(occ).select(F.col("item").alias("prefix"), F.col("mx").alias("head"))
    text = F.when(F.col("kind") == "S", F.concat(F.lit("<("), "prefix", F.lit(")("), "item", F.lit(")>"))).otherwise(F.concat(F.lit("<("), "prefix", F.lit(" "), "item", F.lit(")>")))
    return pair_stats(occ).join(one, "prefix").select(
        text.alias("pattern"),
        (F.col("head") * F.col("mx")).alias("max_pr"),
        (F.col("head") * F.col("sm")).alias("es_cap"),
        (F.col("head") * F.col("mx") * F.col("ct")).alias("es_cap_loose"),
        F.col("ct").alias("support_rows"),
    )


def item_weight_caps(occ: DataFrame, weights: DataFrame) -> DataFrame:
    """(item, w_cap, w_cap_global) of one-item patterns, all items of the projection taken as live."""
    w = weights.select("item", "weight")
    o = occ.join(w, "item")
    first = o.groupBy("seq_id", "item").agg(F.min("pos").alias("e0"), F.max("weight").alias("own"))
    # the heaviest item after an event, and the heaviest later-named one in it
    after = Window.partitionBy("seq_id").orderBy("pos").rangeBetween(1, Window.unboundedFollowing)
    per = o.groupBy("seq_id", "pos").agg(F.max("weight").alias("w")).withColumn("later", F.max("w").over(after))
    s = first.join(per.select("seq_id", F.col("pos").alias("e0"), "later"), ["seq_id", "e0"]).groupBy("item").agg(F.max("own").alias("own"), F.max("later").alias("later"))
    behind = Window.partitionBy("seq_id", "pos").orderBy(F.desc("item")).rowsBetween(Window.unboundedPreceding, -1)
    i = o.withColumn("beside", F.max("weight").over(behind)).groupBy("item").agg(F.max("beside").alias("beside"))
    top = w.join(occ.select("item").distinct(), "item", "left_semi").agg(F.max("weight").alias("w_cap_global"))
    return s.join(i, "item").crossJoin(top).select("item", F.greatest("own", "later", "beside").alias("w_cap"), "w_cap_global")
