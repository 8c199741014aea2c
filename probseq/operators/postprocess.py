"""What a user does with mined patterns."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from probseq.config import MiningParams
from probseq.functions import patterns as P
from probseq.operators.encode import dictionary
from probseq.operators.measures import global_threshold
from probseq.operators.miner import mine_capped
from probseq.operators.splits import share as split_share


def top_k(result: DataFrame, k: int) -> DataFrame:
    return result.orderBy(F.desc("wes"), "pattern").limit(k)


def top_k_per_length(result: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("length").orderBy(F.desc("wes"), "pattern")
    return result.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def _larger(result: DataFrame) -> DataFrame:
    """Pairs (pattern, of a longer one that contains it); the length and an item decide most pairs before the fold."""
    a = result.select("pattern", "es", "length", P.events("pattern").alias("ev")).alias("a")
    b = result.select("pattern", "es", "length", P.events("pattern").alias("ev"), F.array_distinct(F.flatten(P.events("pattern"))).alias("items"))
    keyed = b.select(F.explode("items").alias("key"), "pattern", "es", "length", "ev").alias("b")
    first = a.select("a.*", F.element_at(F.element_at("ev", 1), 1).alias("key")).alias("a")
    j = first.join(keyed, (F.col("a.key") == F.col("b.key")) & (F.col("b.length") > F.col("a.length")))
    return j.where(P.has(F.col("b.ev"), F.col("a.ev"))).select(F.col("a.pattern").alias("pattern"), F.col("a.es").alias("es"), F.col("b.es").alias("super_es"))


def maximal(result: DataFrame) -> DataFrame:
    """Patterns that no longer pattern of the result contains."""
    return result.join(_larger(result).select("pattern").distinct(), "pattern", "left_anti")


def closed(result: DataFrame, digits: int = 9) -> DataFrame:
    """Patterns without a longer pattern of the same expected support."""
    same = _larger(result).where(F.round("es", digits) == F.round("super_es", digits)).select("pattern").distinct()
    return result.join(same, "pattern", "left_anti")


def rules(result: DataFrame, min_confidence: float) -> DataFrame:
    """(antecedent, consequent, es, confidence): a pattern's last event follows from the events before it.

    The confidence is the expected support of the whole over that of the antecedent.
    """
    ev = result.where("n_events > 1").select("pattern", "es", P.events("pattern").alias("ev"))
    cut = ev.select(P.text(F.slice("ev", 1, F.size("ev") - 1)).alias("antecedent"), P.text(F.slice("ev", F.size("ev"), 1)).alias("consequent"), "es")
    head = result.select(F.col("pattern").alias("antecedent"), F.col("es").alias("_es"))
    return cut.join(head, "antecedent").select("antecedent", "consequent", "es", (F.col("es") / F.col("_es")).alias("confidence")).where(F.col("confidence") >= min_confidence)


def select_patterns(result: DataFrame, item: str | None = None, first: str | None = None, last: str | None = None, lengths: tuple[int, int] | None = None, weights: tuple[float, float] | None = None) -> DataFrame:
    """Rows by items and sizes of their patterns."""
    items = F.flatten(P.events("pattern"))
    out = result
    if item is not None:
        out = out.where(F.array_contains(items, item))
    if first is not None:
        out = out.where(F.element_at(items, 1) == first)
    if last is not None:
        out = out.where(F.element_at(items, -1) == last)
    if lengths is not None:
        out = out.where(F.col("length").between(*lengths))
    if weights is not None:
        out = out.where(F.col("seq_weight").between(*weights))
    return out


def threshold_for(occ: DataFrame, weights: DataFrame | None, k: int, params: MiningParams, rounds: int = 12) -> tuple[float, DataFrame]:
    """(threshold, result): the largest tried threshold with at least k patterns, by halving."""
    d = dictionary(occ, weights).agg((F.sum(F.col("weight") * F.col("occ")) / F.sum("occ")).alias("w")).first()["w"] or 0.0
    high = global_threshold(occ.select("seq_id").distinct().count(), d, 1.0)
    low, best = 0.0, None
    for _ in range(rounds):
        mid = (low + high) / 2 if low else high / 2
        run = mine_capped(occ, weights, params, mid)
        if run.n_frequent >= k:
            low, best = mid, (mid, run.result)
            if run.n_frequent == k:
                break
        else:
            high = mid
    if best is None:
        raise ValueError(f"fewer than {k} patterns at the lowest threshold tried")
    return best


def sample_sequences(occ: DataFrame, share: float, salt: int = 0) -> DataFrame:
    """Whole sequences, by a hash of their id: for choosing thresholds, never for exact output."""
    return occ.where(split_share("seq_id", f"sample{salt}") < share)
