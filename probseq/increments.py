"""Queries of incremental maintenance: splits, tiers after each batch, transitions, a sliding database, completeness.

Their oracles compute the supports of all patterns by batch with plain joins and then apply the rules of the tiers. Counts
and completeness have oracles; times stand in queries of their own.
"""

from __future__ import annotations

import shutil
import tempfile
import uuid
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from probseq import oracles as O
from probseq.config import IncrementParams, MiningParams
from probseq.operators import evaluate
from probseq.operators.baselines import remine_all
from probseq.operators.encode import in_blocks, packed_parts
from probseq.operators.incremental import Maintainer, Shared, ThreeTierMaintainer, TwoTierMaintainer
from probseq.operators.splits import bounds, split_increments
from probseq.sources import tables
from probseq.sources.uncertainty import normal_weights, probability
from probseq.workloads import item_weights, occurrences, query, r6

ENDS = [0.5, 0.75, 1.0]
WORK, SUP, MU, GAMMA = "order_brand", 0.004, 0.7, 0.8


def state_folder(spark: SparkSession) -> str:
    """A folder for state: under the checkpoint folder that the session names, a temporary one only where it names none."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    return f"{base.rstrip('/')}/state-{uuid.uuid4().hex}" if base else "file://" + tempfile.mkdtemp(prefix="probseq-state-")


def drop_folder(path: str) -> None:
    if path.startswith("file://" + tempfile.gettempdir()):
        shutil.rmtree(path.removeprefix("file://"), ignore_errors=True)


TASK = 1_000_000  # lines whose occurrences one task holds, where there are more than two tasks for each core


def dealt(spark: SparkSession, sf_dir: str, work: str, splits: list[list[float]], by: str = "hash") -> DataFrame:
    """The occurrences with the batch of each split (batch_0, batch_1, ..), kept: dealt by the hash of a sequence or
    (sequences being orders) by order date.

    Rows lie by sequence, in tasks large enough that a tree of patterns is not walked for a few sequences each.
    """
    return _dealt(spark, sf_dir, work, splits, by).persist()


def _dealt(spark: SparkSession, sf_dir: str, work: str, splits: list[list[float]], by: str) -> DataFrame:
    tasks = max(2 * spark.sparkContext.defaultParallelism, tables.table(spark, sf_dir, "lineitem").count() // TASK)
    occ = tables.order_brand(spark, sf_dir, tasks) if work == WORK else getattr(tables, work)(spark, sf_dir)
    if by == "hash":
        for k, ends in enumerate(splits):
            occ = split_increments(occ, ends).withColumnRenamed("batch_id", f"batch_{k}")
    else:
        dates = tables.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("seq_id"), F.col("o_orderdate").alias("t"))
        for k, ends in enumerate(splits):
            dates = split_increments(dates, ends, "time", "t").withColumnRenamed("batch_id", f"batch_{k}")
        dates = dates.drop("t").repartition(tasks, "seq_id")
        occ = occ.join(dates.hint("shuffle_hash"), "seq_id")
    occ = occ.withColumn("p", probability())
    return occ if work == WORK else occ.repartition(tasks, "seq_id")


def blocks(spark: SparkSession, sf_dir: str, work: str, splits: list[list[float]], by: str = "hash") -> DataFrame:
    """The occurrences of `dealt` packed, kept: blocks of sequences that are of the same batches."""
    return in_blocks(_dealt(spark, sf_dir, work, splits, by), [f"batch_{k}" for k in range(len(splits))]).persist(StorageLevel.MEMORY_AND_DISK)


def parts_shared(kept: DataFrame, k: int, n: int, weights: DataFrame | None, path: str) -> tuple[list[DataFrame], Shared]:
    """The n batches of split k, whose maintainers find them packed."""
    shared = Shared(weights, path)
    shared.kept = packed_parts(kept, f"batch_{k}", range(n))
    return [shared.kept[b].rows for b in range(n)], shared


def batches(split: DataFrame, k: int, n: int) -> list[DataFrame]:
    """The occurrences of each of the n batches of split k."""
    return [split.where(F.col(f"batch_{k}") == b).select("seq_id", "pos", "item", "p") for b in range(n)]


def parts_of(spark: SparkSession, sf_dir: str, work: str, ends: list[float], by: str = "hash") -> tuple[list[DataFrame], DataFrame]:
    """The occurrences of each batch, and weights."""
    split = dealt(spark, sf_dir, work, [ends], by)
    return batches(split, 0, len(ends)), item_weights(spark, split, work)


def maintained(spark: SparkSession, sf_dir: str, kind: type[Maintainer], upto: int | None = None, weighted: bool = True, local: float | None = None) -> tuple[Maintainer, int]:
    """Orders by month: half of the time span, then two increments of a quarter."""
    kept = blocks(spark, sf_dir, WORK, [ENDS], "time")
    w = _weights(spark, kept).persist() if weighted else None
    path = state_folder(spark)
    parts, shared = parts_shared(kept, 0, len(ENDS), w, path)
    m = kind(MiningParams(SUP, prune="exact"), IncrementParams(MU, GAMMA, local), w, path, shared)
    m.initialize(parts[0])
    last = len(parts) - 1 if upto is None else upto
    for b in range(1, last + 1):
        m.apply(parts[b], b)
    kept.unpersist()
    return m, last


def _weights(spark: SparkSession, kept: DataFrame) -> DataFrame:
    return normal_weights(kept.select(F.explode("names").alias("item")))


# --- splits

_SHARE = "(('0x' || substr(md5('s|' || seq_id::VARCHAR), 1, 4))::INT / 65536.0)"


def _case(x: str, ends: list[float]) -> str:
    return "CASE " + " ".join(f"WHEN {x} < {e} THEN {k}" for k, e in enumerate(ends[:-1])) + f" ELSE {len(ends) - 1} END"


_HALF = bounds(0.5, 5)


@query("split_half_five", f"{O.head('userday_types')} SELECT {_case(_SHARE, _HALF)}::BIGINT AS batch_id, count(DISTINCT seq_id)::BIGINT AS n_seq, count(*)::BIGINT AS n_rows FROM occ0 GROUP BY 1")
def _(spark, sf_dir):
    s = split_increments(occurrences(spark, sf_dir, "userday_types"), _HALF)
    return s.groupBy(F.col("batch_id").cast("long").alias("batch_id")).agg(F.countDistinct("seq_id").alias("n_seq"), F.count(F.lit(1)).alias("n_rows"))


_FIFTH = [0.2, 0.4, 0.6, 0.8, 1.0]


@query(
    "split_months",
    f"WITH o AS (SELECT o_orderkey, epoch_us(o_orderdate) AS t FROM orders), x AS (SELECT (t - (SELECT min(t) FROM o)) / ((SELECT max(t) FROM o) - (SELECT min(t) FROM o) + 1) AS x FROM o) SELECT {_case('x', _FIFTH)}::BIGINT AS batch_id, count(*)::BIGINT AS n_seq FROM x GROUP BY 1",
)
def _(spark, sf_dir):
    o = tables.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("seq_id"), F.col("o_orderdate").alias("t"))
    return split_increments(o, _FIFTH, "time", "t").groupBy(F.col("batch_id").cast("long").alias("batch_id")).agg(F.count(F.lit(1)).alias("n_seq"))


# --- oracles: all supports by batch, then the rules of the tiers

_TIME_SHARE = "SELECT o_orderkey AS seq_id, (epoch_us(o_orderdate) - (SELECT min(epoch_us(o_orderdate)) FROM orders)) / ((SELECT max(epoch_us(o_orderdate)) FROM orders) - (SELECT min(epoch_us(o_orderdate)) FROM orders) + 1) AS x FROM orders"
_HASH_SHARE = f"SELECT seq_id, {_SHARE} AS x FROM (SELECT DISTINCT seq_id FROM occ)"


@dataclass(frozen=True)
class Config:
    """One run of a maintainer: a split of the sequences, thresholds, and whether there are three tiers."""

    split: int
    sup: float
    mu: float
    three: bool
    local: str | None = None


def supports_sql(work: str, splits: list[list[float]], configs: list[Config], depth: int, by: str = "hash", weighted: bool = True) -> str:
    """CTEs up to wes (pat, m, w<split>_<batch>) and th (m<config>_<batch>, g<config>_<batch>), of all patterns that any
    run can track: what stays under every run's lowest threshold in all batches together is cut off."""
    share = _TIME_SHARE if by == "time" else _HASH_SHARE
    cols = ", ".join(f"{_case('x', ends)} AS b{s}" for s, ends in enumerate(splits))
    stats = ", ".join(f"count(DISTINCT seq_id) FILTER (b{s} = {k}) AS n{s}_{k}, sum(weight) FILTER (b{s} = {k}) AS f{s}_{k}, count(*) FILTER (b{s} = {k}) AS c{s}_{k}" for s, ends in enumerate(splits) for k in range(len(ends)))
    limits = []
    for i, c in enumerate(configs):
        for k in range(len(splits[c.split])):
            n, f, o = (" + ".join(f"{x}{c.split}_{j}" for j in range(k + 1)) for x in "nfc")
            limits.append(f"{c.sup} * ({n}) * ({f}) / ({o}) AS m{i}_{k}")
            limits.append(f"{c.local or f'{GAMMA} * {c.mu} * {c.sup} * n{c.split}_{k} * ({f}) / ({o})'} AS g{i}_{k}")
    low = ", ".join(f"{c.mu} * m{i}_0" for i, c in enumerate(configs))
    low += "".join(f", g{i}_{k}" for i, c in enumerate(configs) if c.three for k in range(1, len(splits[c.split])))
    best = " UNION ALL ".join(f"SELECT pat, seq_id, max(pr) AS best, any_value(sw) / {d} AS m FROM l{d} GROUP BY pat, seq_id" for d in range(1, depth + 1))
    sums = ", ".join(f"coalesce(sum(best) FILTER (b{s} = {k}), 0) * any_value(m) AS w{s}_{k}" for s, ends in enumerate(splits) for k in range(len(ends)))
    return f"""{O.head(work, weighted)}, part AS MATERIALIZED (SELECT seq_id, {cols} FROM ({share})),
 st AS MATERIALIZED (SELECT {stats} FROM occ JOIN part USING (seq_id)), th AS MATERIALIZED (SELECT {", ".join(limits)} FROM st),
 thr AS MATERIALIZED (SELECT least({low}) AS t, (SELECT max(weight) FROM occ) AS mw FROM th), {O.levels(depth)},
 best AS (SELECT * FROM ({best})), wes AS MATERIALIZED (SELECT pat, any_value(m) AS m, {sums} FROM best JOIN part USING (seq_id) GROUP BY pat)"""


def _rule(value: str, i: int, k: int, c: Config) -> str:
    last = f" WHEN {value} >= g{i}_{k} * (1 - 1e-9) THEN 'PROMISING'" if c.three and k else ""
    return f"CASE WHEN {value} >= m{i}_{k} * (1 - 1e-9) THEN 'FREQ' WHEN {value} >= {c.mu} * m{i}_{k} * (1 - 1e-9) THEN 'SEMI'{last} END"


def tiers_sql(configs: list[Config], batches: list[int]) -> str:
    """CTEs t<config>_<batch> (pat, m, w, tier, since, exact)."""
    out = ""
    for i, c in enumerate(configs):
        s = c.split
        out += f", t{i}_0 AS MATERIALIZED (SELECT pat, m, w{s}_0 AS w, {_rule(f'w{s}_0', i, 0, c)} AS tier, 0 AS since, TRUE AS exact FROM wes, th WHERE w{s}_0 >= {c.mu} * m{i}_0 * (1 - 1e-9))"
        for k in range(1, batches[s]):
            limit = f"g{i}_{k}" if c.three else f"{c.mu} * m{i}_{k}"
            old = f"SELECT t.pat, t.m, t.w + w{s}_{k} AS w, since, exact FROM t{i}_{k - 1} t JOIN wes USING (pat), th WHERE t.w + w{s}_{k} >= {limit} * (1 - 1e-9)"
            new = f" UNION ALL SELECT pat, m, w{s}_{k}, {k}, FALSE FROM wes, th WHERE w{s}_{k} >= g{i}_{k} * (1 - 1e-9) AND pat NOT IN (SELECT pat FROM t{i}_{k - 1})" if c.three else ""
            out += f", t{i}_{k} AS MATERIALIZED (SELECT * FROM (SELECT pat, m, w, {_rule('w', i, k, c)} AS tier, since, exact FROM ({old}{new}), th) WHERE tier IS NOT NULL)"
    return out


# --- tiers of orders by month

_THREE, _TWO = Config(0, SUP, MU, True), Config(0, SUP, MU, False)


def _chain(*configs: Config, weighted: bool = True) -> str:
    return supports_sql(WORK, [ENDS], list(configs), 3, "time", weighted) + tiers_sql(list(configs), [len(ENDS)])


def _state_sql(k: int, *configs: Config, weighted: bool = True) -> str:
    return f"{_chain(*configs, weighted=weighted)} SELECT '<' || pat || '>' AS pattern, {O.r6('w')} AS wes, tier, since::BIGINT AS since_batch, exact FROM t0_{k}"


def _state(kind: type[Maintainer], k: int, **kw):
    def run(spark, sf_dir):
        m, last = maintained(spark, sf_dir, kind, upto=k, **kw)
        return m.tiers(spark, last).select("pattern", r6("wes").alias("wes"), "tier", "since_batch", "exact")

    return run


for _k in (0, 1, 2):
    query(f"tiers_after_batch_{_k}", _state_sql(_k, _THREE))(_state(ThreeTierMaintainer, _k))
query("two_tier_after_batches", _state_sql(2, _TWO))(_state(TwoTierMaintainer, 2))
query("tiers_unweighted", _state_sql(2, _THREE, weighted=False))(_state(ThreeTierMaintainer, 2, weighted=False))
query("tiers_own_local_threshold", _state_sql(2, Config(0, SUP, MU, True, "6.5")))(_state(ThreeTierMaintainer, 2, local=6.5))


@query("tier_transitions", f"{_chain(_THREE)} SELECT '<' || pat || '>' AS pattern, a.tier AS before, b.tier AS after FROM t0_1 a FULL JOIN t0_2 b USING (pat) WHERE a.tier IS DISTINCT FROM b.tier")
def _(spark, sf_dir):
    m, last = maintained(spark, sf_dir, ThreeTierMaintainer)
    return m.transitions(spark, last)


@query("cube_tier_batch", f"{_chain(_THREE)}, s AS (SELECT tier, 0 AS batch_id FROM t0_0 UNION ALL SELECT tier, 1 FROM t0_1 UNION ALL SELECT tier, 2 FROM t0_2) SELECT tier, batch_id::BIGINT AS batch_id, count(*)::BIGINT AS n FROM s GROUP BY CUBE (tier, batch_id)")
def _(spark, sf_dir):
    m, last = maintained(spark, sf_dir, ThreeTierMaintainer)
    both = m.tiers(spark, 0)
    for k in range(1, last + 1):
        both = both.unionByName(m.tiers(spark, k))
    return both.cube("tier", "batch_id").agg(F.count(F.lit(1)).alias("n"))


_SLID = "w - CASE WHEN since = 0 THEN w0_0 ELSE 0 END"


@query(
    "tiers_after_slide",
    f"""{_chain(_THREE)}, lim AS (SELECT {SUP} * (n0_1 + n0_2) * (f0_1 + f0_2) / (c0_1 + c0_2) AS top, {GAMMA} * {MU} * {SUP} * n0_2 * (f0_1 + f0_2) / (c0_1 + c0_2) AS low FROM st),
 slid AS (SELECT pat, {_SLID} AS w, since, exact FROM t0_2 JOIN wes USING (pat)),
 named AS (SELECT pat, w, since, exact, CASE WHEN w >= top * (1 - 1e-9) THEN 'FREQ' WHEN w >= {MU} * top * (1 - 1e-9) THEN 'SEMI' WHEN w >= low * (1 - 1e-9) THEN 'PROMISING' END AS tier FROM slid, lim)
 SELECT '<' || pat || '>' AS pattern, {O.r6('w')} AS wes, tier, since::BIGINT AS since_batch, exact FROM named WHERE tier IS NOT NULL""",
)
def _(spark, sf_dir):
    """The first half leaves the database once both increments have come."""
    m, last = maintained(spark, sf_dir, ThreeTierMaintainer)
    return m.drop_oldest(spark, 0, last + 1).select("pattern", r6("wes").alias("wes"), "tier", "since_batch", "exact")


@query("remine_after_batches", O.mine(WORK, SUP, 3))
def _(spark, sf_dir):
    from probseq.workloads import shown

    parts, w = parts_of(spark, sf_dir, WORK, ENDS, "time")
    return shown(remine_all([_union(parts)], w, MiningParams(SUP, prune="exact"))[-1].result)


# --- completeness against mining everything again


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@dataclass(frozen=True)
class Study:
    """Runs over one workload; `depth` is one more than the longest pattern that any of them tracks."""

    work: str
    splits: list[list[float]]
    configs: list[Config]
    depth: int
    by: str = "hash"

    def sql(self) -> str:
        batches = [len(e) for e in self.splits]
        rows = []
        for i, c in enumerate(self.configs):
            s, last = c.split, batches[c.split] - 1
            total = " + ".join(f"w{s}_{k}" for k in range(last + 1))
            rows.append(f"""SELECT {self.splits[s][0]}::DOUBLE AS first, {c.sup}::DOUBLE AS min_sup, {c.mu}::DOUBLE AS mu, '{"three" if c.three else "two"}' AS tiers,
  (SELECT count(*) FROM t{i}_{last})::BIGINT AS tracked, (SELECT count(*) FROM t{i}_{last} WHERE tier = 'FREQ')::BIGINT AS found,
  (SELECT count(*) FROM wes, th WHERE {total} >= m{i}_{last} * (1 - 1e-9))::BIGINT AS reference,
  (SELECT count(*) FROM wes JOIN t{i}_{last} USING (pat), th WHERE tier = 'FREQ' AND {total} >= m{i}_{last} * (1 - 1e-9))::BIGINT AS common""")
        done = "SELECT *, round(CASE WHEN reference > 0 THEN 100.0 * common / reference ELSE 100.0 END, 6)::DOUBLE AS completeness, round(CASE WHEN found > 0 THEN 100.0 * common / found ELSE 100.0 END, 6)::DOUBLE AS precision FROM"
        return f"{supports_sql(self.work, self.splits, self.configs, self.depth, self.by)}{tiers_sql(self.configs, batches)} {done} ({' UNION ALL '.join(rows)})"

    def run(self, spark: SparkSession, sf_dir: str, share: bool = True) -> list[tuple]:
        """(first, min_sup, mu, tiers, tracked, found, reference, common, seconds) of every run.

        With `share` the runs share what they have in common, the lowest thresholds first; times are then not comparable.
        """
        out, whole = [], {}
        if share:
            kept = blocks(spark, sf_dir, self.work, self.splits, self.by)
            w = _weights(spark, kept).persist()
        else:
            split = dealt(spark, sf_dir, self.work, self.splits, self.by)
            everything, w = split.select("seq_id", "pos", "item", "p"), item_weights(spark, split, self.work).persist()
        reference = Shared(w, "")  # the whole is the same in all splits
        if share:
            reference.kept = packed_parts(kept)
            everything = reference.kept[0].rows
        for s, ends in enumerate(self.splits):
            parts, shared = parts_shared(kept, s, len(ends), w, state_folder(spark)) if share else (batches(split, s, len(ends)), None)
            own = [c for c in self.configs if c.split == s]
            for c in sorted(own, key=lambda c: (c.sup * c.mu, not c.three)) if share else own:
                params = MiningParams(c.sup, prune="exact")
                if not whole:
                    reference.mine(everything, replace(params, min_sup=min(x.sup for x in self.configs)), None, 0)
                    reference.close()
                if c.sup not in whole:
                    whole[c.sup] = {r["pattern"] for r in reference.mine(everything, params, None, 0).result.select("pattern").collect()}
                m = (ThreeTierMaintainer if c.three else TwoTierMaintainer)(params, IncrementParams(c.mu, GAMMA), w, state_folder(spark), shared)

                def go(m=m, parts=parts):
                    m.initialize(parts[0])
                    for b in range(1, len(parts)):
                        m.apply(parts[b], b)
                    return {r["pattern"]: r["tier"] for r in m.tiers(spark, len(parts) - 1).select("pattern", "tier").collect()}

                state, seconds = evaluate.timed(go)
                drop_folder(m.path)
                found = {p for p, t in state.items() if t == "FREQ"}
                out.append((ends[0], c.sup, c.mu, "three" if c.three else "two", len(state), len(found), len(whole[c.sup]), len(found & whole[c.sup]), seconds))
            if shared:
                shared.close()
                drop_folder(shared.path)
        w.unpersist()
        spark.catalog.clearCache()
        place = {(self.splits[c.split][0], c.sup, c.mu, "three" if c.three else "two"): k for k, c in enumerate(self.configs)}
        return sorted(out, key=lambda r: place[r[:4]])


_COLS = "first double, min_sup double, mu double, tiers string, tracked long, found long, reference long, common long"


def _study(name: str, study: Study) -> None:
    @query(name, study.sql())
    def _(spark, sf_dir):
        rows = spark.createDataFrame([r[:-1] for r in study.run(spark, sf_dir)], _COLS)
        share = lambda of: F.round(F.when(F.col(of) > 0, 100.0 * F.col("common") / F.col(of)).otherwise(100.0), 6)
        return rows.withColumn("completeness", share("reference")).withColumn("precision", share("found"))


def _both(splits: list[int], sups: list[float], mus: list[float]) -> list[Config]:
    return [Config(s, sup, mu, three) for s in splits for sup in sups for mu in mus for three in (True, False)]


_FIFTHS = [0.2, 0.6, 1.0]
_study("completeness_by_mu", Study(WORK, [_FIFTHS], _both([0], [SUP], [1.0, 0.8, 0.65, 0.5]), 3, "time"))
_study("completeness_by_mu_baskets", Study("customer_type_size", [[0.5, 1.0]], _both([0], [0.12], [1.0, 0.8]), 3))
_study("completeness_by_min_sup", Study(WORK, [_FIFTHS], _both([0], [0.003, 0.004, 0.005], [0.8]), 3, "time"))
_study("completeness_by_initial_size", Study("customer_brand", [[0.4, 0.7, 1.0], [0.8, 1.0]], _both([0, 1], [0.15], [0.9]), 3))


@query("tradeoff_by_mu")
def _(spark, sf_dir):
    """Completeness against seconds; times have no oracle."""
    study = Study(WORK, [ENDS], _both([0], [SUP], [1.0, 0.7]), 3, "time")
    rows = [(mu, tiers, 100.0 * common / reference if reference else 100.0, seconds) for _, _, mu, tiers, _, _, reference, common, seconds in study.run(spark, sf_dir, share=False)]
    return spark.createDataFrame(rows, "mu double, tiers string, completeness double, seconds double")
