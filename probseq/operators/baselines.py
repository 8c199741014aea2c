"""The methods that the miners are compared with."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.config import SLACK, MiningParams
from probseq.functions import patterns as P
from probseq.operators.encode import dictionary
from probseq.operators.measures import seq_weight
from probseq.operators.miner import RESULT, MiningRun, mine_capped
from probseq.operators.support import expected_support, max_pr_in_seq
from probseq.sources.uncertainty import certain


def mine_loose(occ: DataFrame, weights: DataFrame | None, params: MiningParams, threshold: float | None = None) -> MiningRun:
    """Prefix growth under the loose support cap, then the quadratic support check of every candidate by itself."""
    run = mine_capped(occ, weights, replace(params, support_cap="loose", verify="fused"), threshold)
    if run.rows:
        again = expected_support(occ, run.candidates.select("pattern"), None, "pairwise").select("pattern", F.col("es").alias("_es"))
        run.result = run.result.join(again, "pattern").select("pattern", "length", "n_events", "support", F.col("_es").alias("es"), "seq_weight", (F.col("_es") * F.col("seq_weight")).alias("wes"))
    return run


def mine_separate(occ: DataFrame, weights: DataFrame, min_es: float, min_weight: float, params: MiningParams | None = None) -> DataFrame:
    """Patterns with expected support over one threshold and weight over another."""
    run = mine_capped(occ, None, params or MiningParams(0.0), min_es)
    w = seq_weight(run.result.select("pattern"), weights).withColumnRenamed("seq_weight", "_w")
    return run.result.join(w, "pattern").where(F.col("_w") >= min_weight).select("pattern", "length", "n_events", "support", "es", F.col("_w").alias("seq_weight"), (F.col("es") * F.col("_w")).alias("wes"))


def mine_global_weight(occ: DataFrame, weights: DataFrame | None, params: MiningParams, threshold: float | None = None) -> MiningRun:
    """The heaviest item of the database as the weight cap."""
    return mine_capped(occ, weights, replace(params, weight_cap="global"), threshold)


def mine_precise(occ: DataFrame, min_count: float, params: MiningParams | None = None) -> MiningRun:
    """Prefix projection on certain data: expected support is support."""
    return mine_capped(certain(occ), None, params or MiningParams(0.0), min_count)


def mine_generate_test(occ: DataFrame, weights: DataFrame | None, threshold: float, max_len: int = 6) -> DataFrame:
    """Level-wise: join patterns that overlap in all but their ends, test them in a scan, keep those that can grow.

    A level keeps patterns whose exact expected support times the heaviest weight reaches the threshold.
    """
    spark = occ.sparkSession
    top = dictionary(occ, weights).agg(F.max("weight").alias("w")).first()["w"]
    if top is None:
        return spark.createDataFrame([], RESULT)
    level = [((("S", r["item"]),)) for r in occ.select("item").distinct().collect()]
    done: list[tuple] = []
    while level:
        texts = spark.createDataFrame([(P.to_text(s),) for s in level], "pattern string")
        tested = expected_support(occ, texts, weights).collect()
        alive = [P.to_steps(r["pattern"]) for r in tested if r["es"] * top >= threshold * (1 - SLACK)]
        done += [(r["pattern"], r["support"], r["es"], r["seq_weight"], r["wes"]) for r in tested if r["wes"] >= threshold * (1 - SLACK)]
        if not alive or len(alive[0]) >= max_len:
            break
        level = sorted(_joined(alive))
    rows = [(p, len(P.to_steps(p)), p.count("("), s, es, w, wes) for p, s, es, w, wes in done]
    return spark.createDataFrame(rows, RESULT)


def _joined(alive: list[P.Steps]) -> set[P.Steps]:
    """Patterns one longer whose first and last sub-patterns are both alive."""
    def tail(s: P.Steps) -> P.Steps:
        rest = s[1:]
        return (("S", rest[0][1]), *rest[1:]) if rest else ()

    out = set()
    if len(alive[0]) == 1:
        names = sorted(s[0][1] for s in alive)
        for a in names:
            for b in names:
                out.add((("S", a), ("S", b)))
                if b > a:
                    out.add((("S", a), ("I", b)))
        return out
    by_head: dict[P.Steps, list[P.Steps]] = {}
    for s in alive:
        by_head.setdefault(s[:-1], []).append(s)
    for s in alive:
        for t in by_head.get(tail(s), []):
            kind, item = t[-1]
            if kind == "S" or item > s[-1][1]:
                out.add((*s, (kind, item)))
    return out


def mine_probabilistic(occ: DataFrame, min_count: int, tau: float, max_len: int | None = None, min_es: float | None = None) -> DataFrame:
    """Patterns that at least `min_count` sequences have with probability tau or more, sequences being independent.

    P(support >= min_count) is a Poisson-binomial tail over the best match probabilities, by dynamic programming in one
    fold per pattern. By Markov's inequality es >= tau * min_count is needed, so that threshold finds the candidates.
    """
    run = mine_capped(occ, None, MiningParams(0.0, max_len=max_len), min_es if min_es is not None else tau * min_count)
    best = max_pr_in_seq(occ, run.result.select("pattern"))
    ps = best.groupBy("pattern").agg(F.array_sort(F.collect_list("best")).alias("ps"), F.sum("best").alias("es"))
    start = F.array_repeat(F.lit(0.0), F.lit(min_count))
    # d[k]: probability of k matches so far, k below min_count
    first = F.transform(start, lambda x, i: F.when(i == 0, 1.0).otherwise(x))
    step = lambda d, p: F.transform(d, lambda x, i: x * (1 - p) + F.when(i > 0, F.coalesce(F.get(d, i - 1), F.lit(0.0))).otherwise(0.0) * p)
    less = F.aggregate(F.aggregate("ps", first, step), F.lit(0.0), lambda a, x: a + x)
    return ps.select("pattern", "es", (1 - less).alias("probability")).where(F.col("probability") >= tau)


def mine_bruteforce(occ: DataFrame, weights: DataFrame | None, threshold: float, max_len: int) -> DataFrame:
    """All patterns up to a length by plain joins, with no caps and no suffix maxima."""
    o = occ.select("seq_id", F.col("pos").cast("long").alias("pos"), "item", "p")
    level = o.select("seq_id", "pos", F.concat(F.lit("<("), "item", F.lit(")>")).alias("pattern"), F.col("item").alias("last"), F.col("p").alias("pr"))
    out = None
    for d in range(1, max_len + 1):
        es = level.groupBy("pattern", "seq_id").agg(F.max("pr").alias("best")).groupBy("pattern").agg(F.sum("best").alias("es"), F.count(F.lit(1)).alias("support"))
        out = es if out is None else out.unionByName(es)
        if d < max_len:
            left = level.withColumnRenamed("pos", "end")
            s = left.join(o, "seq_id").where("pos > end").select("seq_id", "pos", F.concat(F.expr("left(pattern, length(pattern) - 1)"), F.lit("("), "item", F.lit(")>")).alias("pattern"), F.col("item").alias("last"), (F.col("pr") * F.col("p")).alias("pr"))
            i = left.join(o, "seq_id").where("pos = end and item > last").select("seq_id", "pos", F.concat(F.expr("left(pattern, length(pattern) - 2)"), F.lit(" "), "item", F.lit(")>")).alias("pattern"), F.col("item").alias("last"), (F.col("pr") * F.col("p")).alias("pr"))
            level = s.unionByName(i).groupBy("seq_id", "pos", "pattern", "last").agg(F.max("pr").alias("pr"))
    full = out.join(seq_weight(out.select("pattern"), weights), "pattern")
    return full.select("pattern", P.length("pattern").alias("length"), P.n_events("pattern").alias("n_events"), "support", "es", "seq_weight", (F.col("es") * F.col("seq_weight")).alias("wes")).where(F.col("wes") >= threshold * (1 - SLACK))


def remine_all(parts: list[DataFrame], weights: DataFrame | None, params: MiningParams) -> list[MiningRun]:
    """The batch miner from scratch after each increment."""
    runs, whole = [], None
    for p in parts:
        whole = p if whole is None else whole.unionByName(p)
        runs.append(mine_capped(whole, weights, params))
    return runs


def poisson_binomial_tail(ps: list[float], k: int) -> float:
    """P(at least k successes), for tests."""
    d = np.zeros(len(ps) + 1)
    d[0] = 1
    for p in ps:
        d[1:] = d[1:] * (1 - p) + d[:-1] * p
        d[0] *= 1 - p
    return float(d[k:].sum())

