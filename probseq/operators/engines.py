"""One growth pass over the data: statistics of all extensions of the live nodes of a level.

Both engines yield (node, kind, item, mx, sm, ct): for kind S and I the maximum, sum and count, over sequences, of the
best (suffix-maximum) probability with which `item` extends `node`; for kind E the expected support of the node itself
(sm) and the number of sequences that have it (ct). Items are ids in order of their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from probseq.operators.encode import pack, suffix_max
from probseq.operators.kernel import Tree, batches_of, walk

STATS = "node long, kind string, item int, mx double, sm double, ct long"
ROOT = -1


class ArrowEngine:
    """Recomputes the states of live nodes from the tree in every pass: no frontier is stored, no raw row is shuffled.

    A pass is a narrow scan of the packed sequences; what is shuffled are partial sums, at most one row per partition
    and live extension.
    """

    def __init__(self, occ: DataFrame, ids: DataFrame, cooccurring: bool = False):
        self.packed = pack(occ, ids).persist(StorageLevel.MEMORY_AND_DISK)
        self.cooccurring, self.n_items = cooccurring, ids.count()

    def close(self) -> None:
        self.packed.unpersist()

    def level(self, tree: Tree, groups: list[np.ndarray]) -> Iterator[DataFrame]:
        """Statistics of the live nodes of `tree` (an empty tree: of the root), one frame for each group of them."""
        for live in groups:
            yield self._group(tree, live)

    def _group(self, tree: Tree, live: np.ndarray) -> DataFrame:
        wanted, cooccurring, n_items = set(live.tolist()), self.cooccurring, self.n_items
        needed, at = set(), live[live >= 0]
        while len(at):  # only branches that lead to a live node
            needed.update(at.tolist())
            at = np.unique(tree.parent[at])
            at = at[at >= 0]
        children = {k: [c for c in own if c in needed] for k, own in tree.children().items() if k == ROOT or k in needed}
        item_of = tree.item.tolist()

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[tuple[int, str], list[np.ndarray]] = {}  # (node, kind) -> items, maxima, sums, counts of one batch each
            es: dict[int, list] = {}
            size = 0

            def flush() -> pa.RecordBatch:
                cols = []
                for (k, kind), parts in held.items():
                    mx, sm, ct = np.zeros(n_items), np.zeros(n_items), np.zeros(n_items, np.int64)
                    for i, m, s, c in parts:
                        mx[i] = np.maximum(mx[i], m)
                        sm[i] += s
                        ct[i] += c
                    hit = np.flatnonzero(ct)
                    cols.append((np.full(len(hit), k), [kind] * len(hit), hit, mx[hit], sm[hit], ct[hit]))
                if es:
                    n = np.array(list(es))
                    v = np.array([es[k] for k in n.tolist()])
                    cols.append((n, ["E"] * len(n), np.full(len(n), -1), v[:, 0], v[:, 1], v[:, 2].astype(np.int64)))
                held.clear()
                es.clear()
                types = [pa.int64(), pa.string(), pa.int32(), pa.float64(), pa.float64(), pa.int64()]
                arrays = [pa.array([x for c in cols for x in c[1]], t) if k == 1 else pa.array(np.concatenate([c[k] for c in cols]), t) for k, t in enumerate(types)]
                return pa.RecordBatch.from_arrays(arrays, ["node", "kind", "item", "mx", "sm", "ct"])

            for b in batches:
                for _, batch in batches_of(b.column(0), n_items):

                    def visit(k, state, batch=batch):
                        nonlocal size
                        if k not in wanted:
                            return
                        if state is not None:
                            own = es.setdefault(k, [0.0, 0.0, 0])
                            own[0] = max(own[0], float(state.best.max()))
                            own[1] += float(state.best.sum())
                            own[2] += len(state.rows)
                        for kind, *part in batch.extensions(state, item_of[k] if k != ROOT else -1, cooccurring):
                            held.setdefault((k, kind), []).append(part)
                            size += len(part[0])

                    if ROOT in wanted:
                        visit(ROOT, None)
                    else:
                        walk(batch, tree, children, visit)
                    if size > 1 << 20 and held:
                        size = 0
                        yield flush()
            if held or es:
                yield flush()

        parts = self.packed.select("events").mapInArrow(run, STATS)
        return parts.groupBy("node", "kind", "item").agg(F.max("mx").alias("mx"), F.sum("sm").alias("sm"), F.sum("ct").alias("ct"))


class RelationalEngine:
    """The same pass as joins and aggregates over a stored frontier (node, seq_id, pos, pr).

    Occurrences and frontier are kept partitioned by sequence, so that the joins of a level move no rows.
    """

    def __init__(self, occ: DataFrame, ids: DataFrame, cooccurring: bool = False):
        known = suffix_max(occ.join(ids, "item").select("seq_id", F.col("pos").cast("long").alias("pos"), F.col("id").alias("item"), "p"))
        self.occ = known.repartition("seq_id").persist(StorageLevel.MEMORY_AND_DISK)
        self.cooccurring, self.frontiers, self.fresh = cooccurring, [], []

    def close(self) -> None:
        self.occ.unpersist()
        for f in self.frontiers + self.fresh:
            f.unpersist()

    def level(self, tree: Tree, groups: list[np.ndarray]) -> Iterator[DataFrame]:
        """As ArrowEngine.level; the frontiers of all groups become the next level's parents once the level is done."""
        o = self.occ
        if groups[0].tolist() == [ROOT]:
            per = o.groupBy("seq_id", "item").agg(F.max("p_sfx").alias("best")).withColumn("node", F.lit(ROOT).cast("long"))
            yield _stats(per, "S")
            return
        old, self.fresh = self.frontiers, []
        for live in groups:
            yield self._group(tree, live)
        self.frontiers, self.fresh = self.fresh, []
        for f in old:
            f.unpersist()

    def _group(self, tree: Tree, live: np.ndarray) -> DataFrame:
        o, spark = self.occ, self.occ.sparkSession
        kids = spark.createDataFrame([(int(k), int(tree.parent[k]), "S" if tree.kind[k] == b"S" else "I", int(tree.item[k])) for k in live], "node long, parent long, kind string, item int")
        small = F.broadcast(kids)
        if not self.frontiers:
            now = o.join(small, "item").select("node", "seq_id", "pos", F.col("p").alias("pr"))
        else:
            parent = reduce(DataFrame.unionByName, self.frontiers).select(F.col("node").alias("parent"), "seq_id", "pos", "pr")
            i = parent.join(small.where("kind = 'I'"), "parent").join(o, ["seq_id", "pos", "item"]).select("node", "seq_id", "pos", (F.col("pr") * F.col("p")).alias("pr"))
            s_kids = small.where("kind = 'S'")
            ends = parent.join(s_kids, "parent").select("seq_id", "node", "item", "pos", "pr", F.lit(None).cast("double").alias("p"))
            items = ends.select("seq_id", "node", "item").distinct().join(o, ["seq_id", "item"]).select("seq_id", "node", "item", "pos", F.lit(None).cast("double").alias("pr"), "p")
            before = Window.partitionBy("seq_id", "node").orderBy("pos").rangeBetween(Window.unboundedPreceding, -1)
            s = ends.unionByName(items).withColumn("best", F.max("pr").over(before)).where("p is not null and best > 0").select("node", "seq_id", "pos", (F.col("best") * F.col("p")).alias("pr"))
            now = i.unionByName(s)
        now = now.repartition("seq_id").persist(StorageLevel.MEMORY_AND_DISK)
        self.fresh.append(now)
        own = now.groupBy("node", "seq_id").agg(F.max("pr").alias("best")).withColumn("item", F.lit(-1))
        first = now.groupBy("seq_id", "node").agg(F.min("pos").alias("e0"))
        s = first.join(o, "seq_id").where(F.col("pos") > F.col("e0")).groupBy("node", "seq_id", "item").agg(F.max("p_sfx").alias("best"))
        last = F.broadcast(kids.select("node", F.col("item").alias("last")))
        p = "p" if self.cooccurring else "p_sfx"
        i = now.select("node", "seq_id", "pos").join(last, "node").join(o, ["seq_id", "pos"]).where(F.col("item") > F.col("last")).groupBy("node", "seq_id", "item").agg(F.max(p).alias("best"))
        return _stats(own, "E").unionByName(_stats(s, "S")).unionByName(_stats(i, "I"))


def _stats(per: DataFrame, kind: str) -> DataFrame:
    return per.groupBy("node", F.lit(kind).alias("kind"), "item").agg(F.max("best").alias("mx"), F.sum("best").alias("sm"), F.count(F.lit(1)).alias("ct"))
