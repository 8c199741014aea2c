"""The experiments: candidates, runtimes, caps, weights, support passes. Counts have oracles; times stand in queries of their own."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


from probseq import oracles as O
from probseq.config import MiningParams
from probseq.operators import evaluate, support
from probseq.operators.baselines import mine_loose
from probseq.operators.miner import mine_capped
from probseq.workloads import _FOUND, item_weights, mined, occurrences, query, r6

RUN = "workload string, min_sup double, support_cap string, weight_cap string, candidates long, frequent long, false_ratio double"
CLICKS = [0.0005, 0.00075, 0.001, 0.0015, 0.002]
DAYS = [0.002, 0.005, 0.01, 0.02, 0.03]


def candidate_rows(spark: SparkSession, sf_dir: str, work: str, runs: list[tuple[float, str, str]], weighted: bool) -> DataFrame:
    """(min_sup, support cap, weight cap) runs, each candidate verified."""
    occ = occurrences(spark, sf_dir, work).persist()
    w = item_weights(spark, occ, work).persist() if weighted else None
    rows = []
    for sup, cap, weight in runs:
        c = evaluate.candidate_counts(mine_capped(occ, w, MiningParams(sup, support_cap=cap, weight_cap=weight, verify="final_scan")))
        rows.append((work, sup, cap, weight, c["candidates"], c["frequent"], round(c["false_ratio"], 6)))
    occ.unpersist()
    return spark.createDataFrame(rows, RUN)


def _candidates(name: str, work: str, runs: list[tuple[float, str, str]], depth: int, longest: int, weighted: bool) -> None:
    query(name, O.candidate_counts(work, runs, depth, longest, weighted))(lambda spark, sf_dir: candidate_rows(spark, sf_dir, work, runs, weighted))


_candidates("false_candidate_ratio", "userday_types", [(s, c, "local") for s in DAYS for c in ("tight", "loose")], 7, 4, False)
_candidates("false_candidate_ratio_clicks", "userday_clicks", [(s, c, "local") for s in CLICKS for c in ("tight", "loose")], 5, 3, False)
_candidates("candidate_count_by_cap", "userday_clicks", [(0.0015, c, w) for c in ("tight", "loose") for w in ("local", "global")], 5, 3, True)


@query("runtime_tight_and_loose")
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types").persist()
    occ.count()
    rows = []
    for sup in (0.01, 0.02):
        p = MiningParams(sup, max_len=3)
        tight, t = evaluate.timed(lambda p=p: mine_capped(occ, None, p))
        # the baseline's quadratic check is part of its time
        loose, u = evaluate.timed(lambda p=p: mine_loose(occ, None, p).result.count())
        rows.append((sup, tight.n_frequent, loose, t, u, evaluate.speedup(u, t)))
    return spark.createDataFrame(rows, "min_sup double, frequent_tight long, frequent_loose long, tight_s double, loose_s double, speedup double")


@query("bound_gap")
def _(spark, sf_dir):
    return evaluate.bound_gap(mined(spark, sf_dir, "userday_types", 0.005))


_SCHEMES = [("userday_types", 0.005, 4), ("order_brand", 0.004, 3), ("segment_brand_type", 0.02, 3)]


@query("weighted_and_unweighted", " UNION ALL ".join(f"SELECT '{w}' AS workload, {str(x).upper()} AS weighted, * FROM ({O.mined(w, s, d, weighted=x)} SELECT {O.r6('(SELECT t FROM thr)')} AS threshold, count(*)::BIGINT AS frequent FROM found)" for w, s, d in _SCHEMES for x in (True, False)))
def _(spark, sf_dir):
    rows = []
    for work, sup, _ in _SCHEMES:
        for weighted in (True, False):
            run = mined(spark, sf_dir, work, sup, weighted, prune="exact")
            rows.append((work, weighted, run.threshold, run.n_frequent))
    return spark.createDataFrame(rows, "workload string, weighted boolean, threshold double, frequent long").withColumn("threshold", r6("threshold"))


_FACTORS = [(f, s) for f in (0.8, 1.0, 1.2) for s in (0.002, 0.005)]


@query(
    "weight_factor_and_support",
    f"{O.head('userday_types')}, {O.thresholds(0.002, 0.8)}, {O.levels(4)}, n AS (SELECT count(DISTINCT seq_id) * sum(weight) / count(*) AS n FROM occ) "
    + " UNION ALL ".join(f"SELECT {f}::DOUBLE AS wgt_fct, {s}::DOUBLE AS min_sup, count(*)::BIGINT AS frequent FROM ({O.all_levels(4)}), n WHERE es * seq_weight >= {s} * {f} * n * (1 - 1e-9)" for f, s in _FACTORS),
)
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types").persist()
    w = item_weights(spark, occ, "userday_types")
    rows = [(f, s, mine_capped(occ, w, MiningParams(s, wgt_fct=f, prune="exact")).n_frequent) for f, s in _FACTORS]
    return spark.createDataFrame(rows, "wgt_fct double, min_sup double, frequent long")


_K = f"{_FOUND}, k AS (SELECT seq_id, count(DISTINCT pos) AS k FROM occ GROUP BY seq_id), n AS (SELECT count(*) AS nodes FROM (SELECT DISTINCT list_slice(string_split(pat[2:-2], ')('), 1, i) AS e FROM (SELECT pat, unnest(range(1, length + 1)) AS i FROM found)))"


@query("work_counters", f"{_K} SELECT nodes::BIGINT AS nodes, (SELECT count(*) FROM k)::BIGINT AS n_seq, (nodes * (SELECT sum(k) FROM k))::BIGINT AS cells, ((SELECT sum(length - 1) FROM found) * (SELECT sum(k * (k - 1) / 2) FROM k))::BIGINT AS pairs FROM n")
def _(spark, sf_dir):
    occ = occurrences(spark, sf_dir, "userday_types")
    return evaluate.work_counters(occ, mined(spark, sf_dir, "userday_types", 0.002).result)


@query("tree_space", f"{_K} SELECT (SELECT count(*) FROM found)::BIGINT AS patterns, (SELECT sum(length) FROM found)::BIGINT AS items, nodes::BIGINT AS nodes FROM n")
def _(spark, sf_dir):
    return evaluate.tree_space(mined(spark, sf_dir, "userday_types", 0.002).result)


_CUTS = (10, 20, 40, 80)


def _pairs_of(spark: SparkSession, occ: DataFrame) -> DataFrame:
    names = sorted(r["item"] for r in occ.select("item").distinct().collect())
    return spark.createDataFrame([(f"<({a})({b})>",) for a in names for b in names], "pattern string")


@query(
    "support_pass_counts",
    f"{O.head('user_types')}, i AS (SELECT count(DISTINCT item) AS i FROM occ) "
    + " UNION ALL ".join(f"SELECT {k} AS k, ((any_value(i) * any_value(i) + any_value(i)) * sum(x))::BIGINT AS cells, (any_value(i) * any_value(i) * sum(x * (x - 1) / 2))::BIGINT AS pairs FROM (SELECT seq_id, count(*) AS x FROM occ WHERE pos <= {k} GROUP BY seq_id), i" for k in _CUTS),
)
def _(spark, sf_dir):
    """Work of the shared pass and of the pattern-wise check on sequences cut to k events: linear against quadratic."""
    occ = occurrences(spark, sf_dir, "user_types").persist()
    pats = _pairs_of(spark, occ)
    rows = [(k, *evaluate.work_counters(occ.where(F.col("pos") <= k), pats).select("cells", "pairs").first()) for k in _CUTS]
    return spark.createDataFrame(rows, "k int, cells long, pairs long")


@query("support_pass_by_length")
def _(spark, sf_dir):
    """Cells and pair operations on sequences cut to k events: linear against quadratic."""
    occ = occurrences(spark, sf_dir, "user_types").persist()
    pats = _pairs_of(spark, occ)
    rows = []
    for k in _CUTS:
        cut = occ.where(F.col("pos") <= k).persist()
        cut.count()
        c = evaluate.work_counters(cut, pats).first()
        _, tree = evaluate.timed(lambda cut=cut: support.expected_support(cut, pats, None, "arrow").collect())
        _, pair = evaluate.timed(lambda cut=cut: support.expected_support(cut, pats, None, "pairwise").collect())
        rows.append((k, c["cells"], c["pairs"], tree, pair))
    return spark.createDataFrame(rows, "k int, cells long, pairs long, tree_s double, pairwise_s double")


@query("scalability_per_increment")
def _(spark, sf_dir):
    """Seconds per increment of both maintainers and of mining everything again."""
    from probseq.config import IncrementParams
    from probseq.increments import drop_folder, parts_of, state_folder
    from probseq.operators.incremental import ThreeTierMaintainer, TwoTierMaintainer

    ends = [0.5, 0.75, 1.0]
    parts, w = parts_of(spark, sf_dir, "userday_clicks", ends)
    p = MiningParams(0.001, prune="exact")
    rows = []
    for kind in (ThreeTierMaintainer, TwoTierMaintainer):
        m = kind(p, IncrementParams(0.8, 0.8), w, state_folder(spark))
        for b, part in enumerate(parts):
            _, s = evaluate.timed((lambda: m.initialize(part)) if not b else (lambda: m.apply(part, b)))  # noqa: B023
            rows.append((b, m.log[-1]["n_seq"], kind.__name__, s))
        drop_folder(m.path)
    whole: DataFrame | None = None
    for b, part in enumerate(parts):
        whole = part if whole is None else whole.unionByName(part)
        run, s = evaluate.timed(lambda: mine_capped(whole, w, p))  # noqa: B023
        rows.append((b, run.stats["n_seq"], "remine_all", s))
    return spark.createDataFrame(rows, "batch long, n_seq long, method string, seconds double")


