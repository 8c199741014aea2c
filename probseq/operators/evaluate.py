"""Cost and accuracy measures of runs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.functions import patterns as P
from probseq.operators.miner import MiningRun


def completeness(found: DataFrame, reference: DataFrame) -> DataFrame:
    """(found_n, reference_n, common_n, pct): the share of the reference's patterns that are found."""
    a = found.select("pattern").distinct().withColumn("_a", F.lit(1))
    b = reference.select("pattern").distinct().withColumn("_b", F.lit(1))
    j = a.join(b, "pattern", "full").agg(F.count("_a").alias("found_n"), F.count("_b").alias("reference_n"), F.count(F.when(F.col("_a").isNotNull() & F.col("_b").isNotNull(), 1)).alias("common_n"))
    return j.withColumn("pct", F.when(F.col("reference_n") > 0, 100.0 * F.col("common_n") / F.col("reference_n")).otherwise(F.lit(100.0)))


def precision(found: DataFrame, reference: DataFrame) -> DataFrame:
    return completeness(reference, found)


def false_negatives(found: DataFrame, reference: DataFrame) -> DataFrame:
    return reference.select("pattern").join(found.select("pattern"), "pattern", "left_anti")


def false_candidates(run: MiningRun) -> DataFrame:
    return run.candidates.join(run.result.select("pattern"), "pattern", "left_anti")


def candidate_counts(run: MiningRun) -> dict:
    n, good = run.n_candidates, run.n_frequent
    return {"candidates": n, "frequent": good, "false_candidates": n - good, "false_ratio": (n - good) / n if n else 0.0}


def candidate_ratio(a: MiningRun, b: MiningRun) -> float:
    """How many times fewer candidates a has than b."""
    return b.n_candidates / a.n_candidates if a.n_candidates else float("nan")


def bound_gap(run: MiningRun) -> DataFrame:
    """(depth, tight_over_es, loose_over_es, n): mean of cap over exact support per level."""
    ok = run.candidates.where("es > 0")
    return ok.groupBy("depth").agg(F.avg(F.col("es_cap") / F.col("es")).alias("tight_over_es"), F.avg(F.col("es_cap_loose") / F.col("es")).alias("loose_over_es"), F.count(F.lit(1)).alias("n"))


def work_counters(occ: DataFrame, patterns: DataFrame) -> DataFrame:
    """(nodes, n_seq, cells, pairs): array cells of the shared tree pass, and event pairs of the pattern-wise check.

    For k events a tree node fills k cells; the pair-wise check of m events compares (m - 1) k (k - 1) / 2 pairs.
    """
    k = occ.groupBy("seq_id").agg(F.countDistinct("pos").alias("k")).agg(F.count(F.lit(1)).alias("n_seq"), F.sum("k").alias("k1"), F.sum(F.col("k") * (F.col("k") - 1) / 2).alias("k2"))
    s = patterns.select(P.steps("pattern").alias("s"), P.n_events("pattern").alias("m"))
    nodes = s.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("s")), lambda x: F.slice("s", 1, x))).alias("s")).distinct().agg(F.count(F.lit(1)).alias("nodes"))
    m = s.agg(F.sum(F.col("m") - 1).alias("m"))
    return k.crossJoin(nodes).crossJoin(m).select("nodes", "n_seq", (F.col("nodes") * F.col("k1")).cast("long").alias("cells"), (F.col("m") * F.col("k2")).cast("long").alias("pairs"))


def tree_space(patterns: DataFrame) -> DataFrame:
    """(patterns, items, nodes): nodes of the shared tree against the items of all patterns written out."""
    s = patterns.select("pattern", P.steps("pattern").alias("s"))
    nodes = s.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("s")), lambda x: F.slice("s", 1, x))).alias("s")).distinct().agg(F.count(F.lit(1)).alias("nodes"))
    return s.agg(F.count(F.lit(1)).alias("patterns"), F.sum(F.size("s")).cast("long").alias("items")).crossJoin(nodes)


def timed(action: Callable):
    """(result, seconds) of something that runs jobs."""
    began = time.time()
    return (out := action()), time.time() - began


def speedup(baseline_s: float, method_s: float) -> float:
    return baseline_s / method_s if method_s else float("inf")
