"""Maintenance of patterns while sequences arrive.

State, one version per batch, is a Parquet directory `state/batch_id=b` of (pattern, es, seq_weight, wes, tier,
since_batch, exact), next to `items/batch_id=b` (how often each item occurred so far) and `size/batch_id=b`. What a batch
itself brought is kept beside it: `gains/batch_id=b` (pattern, es), `own_items` and `own_size`. A batch reads the version
before it and overwrites its own, so applying it again changes nothing. Old sequences are never read, not even to take
back what they gave when the database slides on.

The supports of tracked patterns grow by one tree pass over the increment. A pattern first met in an increment enters
with that increment's support alone, so its value is a lower bound (`exact` is false) and the frequent set is a subset
of the true one.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.config import SLACK, IncrementParams, MiningParams
from probseq.operators.encode import Packed, dictionary, packed_once
from probseq.operators.measures import buffer_threshold, global_threshold, local_threshold
from probseq.operators.miner import MiningRun, mine_capped
from probseq.operators.support import expected_support, packed_support

STATE = "pattern string, es double, seq_weight double, wes double, tier string, since_batch long, exact boolean"
FREQ, SEMI, PROMISING = "FREQ", "SEMI", "PROMISING"


def tier_of(wes, min_wes: float, buffer: float, local: float | None):
    """First match of frequent, semi-frequent, promising; null for none. Works on a column."""
    low = 1 - SLACK
    c = F.when(wes >= min_wes * low, FREQ).when(wes >= buffer * low, SEMI)
    return c if local is None else c.when(wes >= local * low, PROMISING)


class Shared:
    """What several maintainers of the same increments have in common, found once: packed sequences, counts (their tables lie
    under `path`) and supports of each increment, and its patterns at the lowest threshold so far, of which a higher one
    takes a part. They take the same steps. The driver holds items and patterns only; `close` gives the sequences back."""

    def __init__(self, weights: DataFrame | None, path: str):
        self.weights, self.path = weights, path.rstrip("/")
        self.sizes: dict[int, tuple[float, int, int]] = {}
        self.mined: dict[tuple, MiningRun] = {}
        self.gained: dict[tuple, dict[str, float]] = {}
        self.kept: dict[int, Packed] = {}

    def packed(self, occ: DataFrame, batch_id: int) -> Packed:
        if batch_id not in self.kept:
            self.kept[batch_id] = packed_once(occ)
        return self.kept[batch_id]

    def close(self) -> None:
        for p in self.kept.values():
            p.close()
        self.kept.clear()

    def mine(self, occ: DataFrame, params: MiningParams, threshold: float | None, batch_id: int) -> MiningRun:
        """As mine_capped; the result is all that reaches the threshold, counters and candidates are those of the run it is taken from."""
        key = (batch_id, replace(params, min_sup=0.0))
        run = self.mined.get(key)
        if run is not None and threshold is None:
            threshold = global_threshold(run.stats["n_seq"], run.stats["wam"], params.min_sup, params.wgt_fct)
        if run is None or threshold < run.threshold:
            run = self.mined[key] = mine_capped(occ, self.weights, params, threshold, self.packed(occ, batch_id) if params.engine == "arrow" else None)
        threshold = run.threshold if threshold is None else threshold
        return replace(run, threshold=threshold, result=run.result.where(F.col("wes") >= threshold * (1 - SLACK)))

    def gains(self, delta: DataFrame, patterns: DataFrame, engine: str, batch_id: int) -> DataFrame:
        """(pattern, es) of patterns in an increment; only those not asked for before are looked up."""
        known = self.gained.setdefault((batch_id, engine), {})
        wanted = [r["pattern"] for r in patterns.select("pattern").distinct().collect()]
        fresh = [x for x in wanted if x not in known]
        if fresh and engine == "arrow":
            known.update(packed_support(self.packed(delta, batch_id), fresh))
        elif fresh:
            found = expected_support(delta, delta.sparkSession.createDataFrame([(x,) for x in fresh], "pattern string"), None, engine)
            known.update((r["pattern"], r["es"]) for r in found.select("pattern", "es").collect())
        return delta.sparkSession.createDataFrame([(x, known[x]) for x in wanted], "pattern string, es double")


class Maintainer:
    """Common steps; `three` adds local mining and the promising tier. Maintainers of the same parts and weights may share work."""

    three = True

    def __init__(self, params: MiningParams, inc: IncrementParams, weights: DataFrame | None, path: str, shared: Shared | None = None):
        self.params, self.inc, self.weights, self.path, self.shared = params, inc, weights, path.rstrip("/"), shared
        self.log: list[dict] = []

    def _at(self, kind: str, batch_id: int) -> str:
        common = self.shared is not None and kind in ("items", "size", "own_items", "own_size")
        return f"{self.shared.path if common else self.path}/{kind}/batch_id={batch_id}"

    def _save(self, df: DataFrame, kind: str, batch_id: int) -> DataFrame:
        at = self._at(kind, batch_id)
        df.write.mode("overwrite").parquet(at)
        return df.sparkSession.read.schema(df.schema).parquet(at)

    def _load(self, spark, kind: str, batch_id: int, schema: str) -> DataFrame:
        return spark.read.schema(schema).parquet(self._at(kind, batch_id))

    def update_stats(self, delta: DataFrame, batch_id: int) -> dict:
        """Adds the item counts and size of the increment to those of the version before, and renews the thresholds."""
        spark = delta.sparkSession
        if self.shared and batch_id in self.shared.sizes:
            return self._limits(*self.shared.sizes[batch_id], batch_id)
        if self.shared and self.params.engine == "arrow":
            packed = self.shared.packed(delta, batch_id)
            counts, n = spark.createDataFrame([x[:3] for x in packed.items if x[1]], "item string, occ long, seqs long").coalesce(1), packed.n_seq
        else:
            counts, n = dictionary(delta).select("item", "occ", "seqs"), delta.select("seq_id").distinct().count()
        own = self._save(counts, "own_items", batch_id)
        self._save(spark.createDataFrame([(n,)], "n long").coalesce(1), "own_size", batch_id)
        total = n
        if batch_id:
            before = self._load(spark, "items", batch_id - 1, "item string, occ long, seqs long")
            own = own.unionByName(before).groupBy("item").agg(F.sum("occ").alias("occ"), F.sum("seqs").alias("seqs"))
            total += self._load(spark, "size", batch_id - 1, "n long").first()["n"]
        items = self._save(own, "items", batch_id)
        self._save(spark.createDataFrame([(total,)], "n long").coalesce(1), "size", batch_id)
        wam = self._wam(items)
        if self.shared:
            self.shared.sizes[batch_id] = wam, total, n
        return self._limits(wam, total, n, batch_id)

    def _wam(self, items: DataFrame) -> float:
        f = "occ" if self.params.freq == "occurrences" else "seqs"
        w = items if self.weights is None else items.join(self.weights.select("item", "weight"), "item", "left")
        weight = F.lit(1.0) if self.weights is None else F.coalesce("weight", F.lit(1.0))
        r = w.agg(F.sum(weight * F.col(f)).alias("wf"), F.sum(f).alias("f")).first()
        return r["wf"] / r["f"] if r["f"] else 0.0

    def _limits(self, wam: float, total: int, n: int, batch_id: int) -> dict:
        """Thresholds of a database of `total` sequences, the last `n` of them new."""
        p = self.params
        min_wes = global_threshold(total, wam, p.min_sup, p.wgt_fct)
        gamma, clamped = self.inc.gamma, False
        if n and gamma * n > total:  # else the limit for deletion would pass that of the buffer
            gamma, clamped = total / n, True
        local = local_threshold(n, wam, p.min_sup, self.inc.mu, gamma, p.wgt_fct)
        out = {"batch_id": batch_id, "delta_n": n, "n_seq": total, "wam": wam, "min_wes": min_wes, "min_wes_buf": buffer_threshold(min_wes, self.inc.mu), "local_wes": local, "clamped": clamped}
        if callable(self.inc.local):
            out["local_wes"] = float(self.inc.local(out))
        elif self.inc.local is not None:
            out["local_wes"] = float(self.inc.local)
        return out

    def initialize(self, occ: DataFrame, batch_id: int = 0) -> DataFrame:
        """Mines with the buffer threshold and labels frequent and semi-frequent patterns."""
        s = self.update_stats(occ, batch_id)
        run = self._mine(occ, s["min_wes_buf"], batch_id)
        state = run.result.select("pattern", "es", "seq_weight", "wes", tier_of(F.col("wes"), s["min_wes"], s["min_wes_buf"], None).alias("tier"), F.lit(batch_id).cast("long").alias("since_batch"), F.lit(True).alias("exact"))
        self.log.append(s | {"candidates": run.n_candidates})
        state = self._save(state.where(F.col("tier").isNotNull()), "state", batch_id)
        self._save(state.select("pattern", "es"), "gains", batch_id)
        return state

    def _mine(self, occ: DataFrame, threshold: float, batch_id: int) -> MiningRun:
        if self.shared:
            return self.shared.mine(occ, self.params, threshold, batch_id)
        return mine_capped(occ, self.weights, self.params, threshold)

    def mine_local(self, delta: DataFrame, s: dict) -> DataFrame:
        return self._mine(delta, s["local_wes"], s["batch_id"]).result

    def update_tracked(self, state: DataFrame, delta: DataFrame, s: dict) -> DataFrame:
        """Adds the increment's supports to tracked patterns; those that miss it only meet the new thresholds."""
        if self.shared:
            gain = self.shared.gains(delta, state, self.params.engine, s["batch_id"])
        else:
            gain = expected_support(delta, state.select("pattern"), None, self.params.engine).select("pattern", "es")
        gain = self._save(gain.where("es > 0"), "gains", s["batch_id"]).withColumnRenamed("es", "_gain")
        es = F.col("es") + F.coalesce("_gain", F.lit(0.0))
        grown = state.join(gain, "pattern", "left").select("pattern", es.alias("es"), "seq_weight", (es * F.col("seq_weight")).alias("wes"), "since_batch", "exact")
        # the deletion test comes first: of the local threshold with three tiers, of the buffer with two
        limit = s["local_wes"] if self.three else s["min_wes_buf"]
        kept = grown.where(F.col("wes") >= limit * (1 - SLACK))
        return kept.withColumn("tier", tier_of(F.col("wes"), s["min_wes"], s["min_wes_buf"], s["local_wes"] if self.three else None)).where(F.col("tier").isNotNull())

    def admit(self, tracked: DataFrame, state: DataFrame, local: DataFrame, s: dict, batch_id: int) -> DataFrame:
        """Patterns of the increment that are not tracked enter with the increment's support."""
        new = local.join(state.select("pattern"), "pattern", "left_anti")
        self._save(new.select("pattern", "es"), "gains_new", batch_id)
        labelled = new.select("pattern", "es", "seq_weight", "wes", F.lit(batch_id).cast("long").alias("since_batch"), F.lit(False).alias("exact"), tier_of(F.col("wes"), s["min_wes"], s["min_wes_buf"], s["local_wes"]).alias("tier"))
        return tracked.unionByName(labelled.where(F.col("tier").isNotNull()))

    def apply(self, delta: DataFrame, batch_id: int) -> DataFrame:
        spark = delta.sparkSession
        s = self.update_stats(delta, batch_id)
        state = self._load(spark, "state", batch_id - 1, STATE)
        new = self.update_tracked(state, delta, s)
        if self.three and s["delta_n"]:
            new = self.admit(new, state, self.mine_local(delta, s), s, batch_id)
        out = self._save(new.select(*[c.split()[0] for c in STATE.split(", ")]), "state", batch_id)
        self.log.append(s)
        return out

    def tiers(self, spark, batch_id: int) -> DataFrame:
        return self._load(spark, "state", batch_id, STATE).withColumn("batch_id", F.lit(batch_id).cast("long"))

    def transitions(self, spark, batch_id: int) -> DataFrame:
        """(pattern, before, after) of patterns whose tier differs from the version before; null: not tracked."""
        a = self.tiers(spark, batch_id - 1).select("pattern", F.col("tier").alias("before"))
        b = self.tiers(spark, batch_id).select("pattern", F.col("tier").alias("after"))
        return a.join(b, "pattern", "full").where(~F.col("before").eqNullSafe(F.col("after")))

    def drop_oldest(self, spark, oldest: int, batch_id: int) -> DataFrame:
        """A sliding database: takes back what batch `oldest` gave, as version `batch_id` after version batch_id - 1.

        Only patterns that were tracked when it came have anything of it: one that was admitted later (or again) starts
        with its own batch. The local threshold stays that of the newest increment.
        """
        state = self._load(spark, "state", batch_id - 1, STATE)
        counts, size = "item string, occ long, seqs long", "n long"
        gone = self._load(spark, "own_items", oldest, counts).select("item", (-F.col("occ")).alias("occ"), (-F.col("seqs")).alias("seqs"))
        left = self._load(spark, "items", batch_id - 1, counts).unionByName(gone).groupBy("item").agg(F.sum("occ").alias("occ"), F.sum("seqs").alias("seqs")).where("occ > 0")
        items = self._save(left, "items", batch_id)
        total = self._load(spark, "size", batch_id - 1, size).first()["n"] - self._load(spark, "own_size", oldest, size).first()["n"]
        self._save(spark.createDataFrame([(total,)], size).coalesce(1), "size", batch_id)
        logged = [x["delta_n"] for x in self.log if not x.get("dropped")]
        newest = logged[-1] if logged else self._load(spark, "own_size", batch_id - 1, size).first()["n"]
        s = self._limits(self._wam(items), total, newest, batch_id) | {"dropped": True}
        gains = self._load(spark, "gains", oldest, "pattern string, es double").select("pattern", F.col("es").alias("_loss"), F.lit(oldest).alias("_upto"))
        if oldest and self.three:  # what was admitted then is its since_batch
            gains = gains.unionByName(self._load(spark, "gains_new", oldest, "pattern string, es double").select("pattern", F.col("es").alias("_loss"), F.lit(oldest).alias("_upto")))
        loss = F.when(F.col("since_batch") <= F.col("_upto"), F.col("_loss")).otherwise(0.0)
        es = F.greatest(F.col("es") - F.coalesce(loss, F.lit(0.0)), F.lit(0.0))
        slid = state.join(gains, "pattern", "left").select("pattern", es.alias("es"), "seq_weight", (es * F.col("seq_weight")).alias("wes"), "since_batch", "exact")
        labelled = slid.withColumn("tier", tier_of(F.col("wes"), s["min_wes"], s["min_wes_buf"], s["local_wes"] if self.three else None)).where("tier is not null and wes > 0")
        self.log.append(s)
        return self._save(labelled.select(*[c.split()[0] for c in STATE.split(", ")]), "state", batch_id)


class ThreeTierMaintainer(Maintainer):
    """Frequent, semi-frequent and promising patterns, with local mining of every increment."""


class TwoTierMaintainer(Maintainer):
    """Frequent and semi-frequent patterns only; nothing new is looked for in an increment."""

    three = False
