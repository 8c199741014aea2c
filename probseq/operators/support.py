"""Exact supports of given patterns: four engines with one result.

arrow       a broadcast tree walks packed sequences in Arrow batches; one narrow scan, partial sums per partition
relational  the tree level by level as joins and windows; prefixes are shared, a running maximum keeps it linear
hof         higher-order functions over packed maps; for a few short patterns
pairwise    every pattern by itself, each event against all earlier ones: the quadratic baseline
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from probseq.functions import patterns as P
from probseq.operators.encode import Packed, batches_in, pack, packed_maps
from probseq.operators.kernel import Families, Tree, batches_of, pairwise_best, totals, walk
from probseq.operators.measures import seq_weight

NODES = 200_000  # nodes of a tree that travels with a task; more patterns make several passes


def tree_of(patterns: list[P.Steps], ids: dict[str, int]) -> tuple[Tree, list[P.Steps]]:
    """Shared-prefix tree of patterns, parents first, and the pattern of each node."""
    found: dict[P.Steps, int] = {}
    for steps in sorted(patterns):
        for k in range(1, len(steps) + 1):
            found.setdefault(steps[:k], len(found))
    nodes = list(found)
    return Tree(
        np.array([found.get(s[:-1], -1) for s in nodes], np.int64),
        np.array([s[-1][0] for s in nodes], "S1"),
        np.array([ids.get(s[-1][1], -1) for s in nodes], np.int64),
    ), nodes


def scan_tree(packed: DataFrame, tree: Tree, names: list[str] | None = None, beside: int = 0) -> DataFrame:
    """(node, es, support, b0, b1, ..) of all nodes that occur: partial sums per partition, then one small aggregate.

    `names` by id are those of rows in blocks. With `beside` items, b<i> of a leaf is the sum over sequences of its best
    probability times that of item i anywhere in the sequence: no pattern that has item i more can have a larger support.
    """
    more = [f"b{i}" for i in range(beside)]

    def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        es, support, families = np.zeros(len(tree.parent)), np.zeros(len(tree.parent), np.int64), Families(tree)
        cross = np.zeros((len(tree.parent), beside)) if beside else None
        for batch in batches_in(parts, names):
            totals(batch, tree, families, es, support, cross)
        hit = np.flatnonzero(support)
        columns = [pa.array(np.ascontiguousarray(cross[hit, i])) for i in range(beside)]
        yield pa.RecordBatch.from_arrays([pa.array(hit, pa.int64()), pa.array(es[hit]), pa.array(support[hit]), *columns], ["node", "es", "support", *more])

    rows = packed.select("events") if names is None else packed
    parts = rows.mapInArrow(run, "node long, es double, support long" + "".join(f", {b} double" for b in more))
    return parts.groupBy("node").agg(F.sum("es").alias("es"), F.sum("support").alias("support"), *(F.sum(b).alias(b) for b in more))


def _groups(patterns: list[P.Steps]) -> list[list[P.Steps]]:
    """Patterns by first item in groups whose trees stay within NODES."""
    out, size = [[]], 0
    for s in sorted(patterns):
        if size + len(s) > NODES and out[-1]:
            out.append([])
            size = 0
        out[-1].append(s)
        size += len(s)
    return out


def _arrow(occ: DataFrame, patterns: list[P.Steps]) -> DataFrame:
    spark = occ.sparkSession
    items = sorted({i for s in patterns for _, i in s})
    ids = {x: k for k, x in enumerate(items)}
    packed = pack(occ, spark.createDataFrame(list(ids.items()), "item string, id int"))
    out = None
    for group in _groups(patterns):
        tree, nodes = tree_of(group, ids)
        names = spark.createDataFrame([(k, P.to_text(s)) for k, s in enumerate(nodes)], "node long, pattern string")
        part = scan_tree(packed, tree).join(names, "node").select("pattern", "es", "support")
        out = part if out is None else out.unionByName(part)
    return out


def packed_support(packed: Packed, patterns: list[str]) -> dict[str, float]:
    """Expected supports of patterns (texts) in sequences that are packed already, by the Arrow engine."""
    ids, out = {x[0]: k for k, x in enumerate(packed.items)}, dict.fromkeys(patterns, 0.0)
    for group in _groups([P.to_steps(x) for x in out]):
        tree, nodes = tree_of(group, ids)
        for r in scan_tree(packed.rows, tree, packed.names).collect() if nodes else []:
            text = P.to_text(nodes[r["node"]])
            if text in out:
                out[text] = r["es"]
    return out


def tree_nodes(patterns: DataFrame) -> DataFrame:
    """(node, parent, depth, kind, item): the shared-prefix tree as rows, keyed by pattern text."""
    s = patterns.select(P.steps("pattern").alias("s"))
    prefix = s.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("s")), lambda k: F.slice("s", 1, k))).alias("s")).distinct()

    def spell(steps):
        body = F.aggregate(steps, F.lit(""), lambda t, x: F.concat(t, F.when(x["kind"] == "S", F.lit(")(")).otherwise(F.lit(" ")), x["item"]))
        return F.concat(F.lit("<"), F.substring(body, 2, 1 << 20), F.lit(")>"))

    last = F.element_at("s", -1)
    return prefix.select(
        spell(F.col("s")).alias("node"),
        F.when(F.size("s") > 1, spell(F.slice("s", 1, F.size("s") - 1))).alias("parent"),
        F.size("s").alias("depth"),
        last["kind"].alias("kind"),
        last["item"].alias("item"),
    )


def _next_level(level: DataFrame, nodes: DataFrame, occ: DataFrame) -> DataFrame:
    """(node, seq_id, pos, pr) of the children of a level's rows.

    S: parent ends and item occurrences of one (node, sequence) are sorted together, and a window keeps the best
    parent value strictly before each occurrence. I: same sequence and event.
    """
    kids = F.broadcast(nodes)
    parent = level.select(F.col("node").alias("parent"), "seq_id", "pos", "pr")
    i = parent.join(kids.where("kind = 'I'"), "parent").join(occ, ["seq_id", "pos", "item"]).select("node", "seq_id", "pos", (F.col("pr") * F.col("p")).alias("pr"))
    s_kids = kids.where("kind = 'S'")
    ends = parent.join(s_kids, "parent").select("node", "seq_id", "pos", "pr", F.lit(None).cast("double").alias("p"))
    wanted = ends.select("node", "seq_id").distinct()
    items = wanted.join(s_kids.select("node", "item"), "node").join(occ, ["seq_id", "item"]).select("node", "seq_id", "pos", F.lit(None).cast("double").alias("pr"), "p")
    before = Window.partitionBy("node", "seq_id").orderBy("pos").rangeBetween(Window.unboundedPreceding, -1)
    s = ends.unionByName(items).withColumn("best", F.max("pr").over(before)).where("p is not null and best > 0").select("node", "seq_id", "pos", (F.col("best") * F.col("p")).alias("pr"))
    return i.unionByName(s)


def _relational(occ: DataFrame, patterns: DataFrame, depth: int) -> DataFrame:
    """Level by level as one lazy plan; `depth` is the longest pattern."""
    nodes = tree_nodes(patterns)
    first = nodes.where("depth = 1").select("node", "item")
    rows = occ.select("seq_id", F.col("pos").cast("long").alias("pos"), "item", "p")
    level = rows.join(F.broadcast(first), "item").select("node", "seq_id", "pos", F.col("p").alias("pr"))
    out = None
    for d in range(1, depth + 1):
        best = level.groupBy("node", "seq_id").agg(F.max("pr").alias("best")).groupBy("node").agg(F.sum("best").alias("es"), F.count(F.lit(1)).alias("support"))
        out = best if out is None else out.unionByName(best)
        if d < depth:
            level = _next_level(level, nodes.where(F.col("depth") == d + 1).select("node", "parent", "kind", "item"), rows)
    return out.withColumnRenamed("node", "pattern")


def _hof(occ: DataFrame, patterns: DataFrame) -> DataFrame:
    """Per (sequence, pattern) a fold over the pattern's events; inside it a fold over the sequence keeps the best so far."""
    seqs = packed_maps(occ).select("seq_id", F.transform("events", lambda e: e["items"]).alias("ev"))
    few = F.broadcast(patterns.select("pattern", P.events("pattern").alias("want")))
    j = seqs.crossJoin(few)  # patterns of a small, given set
    match = lambda e, want: F.aggregate(want, F.lit(1.0), lambda x, i: x * F.coalesce(F.try_element_at(e, i), F.lit(0.0)))
    zero = F.struct(F.array().cast("array<double>").alias("out"), F.lit(0.0).alias("best"))

    def one_event(ends, want):
        """ends[k] is the best value at event k of the prefix; null at the root."""
        def step(acc, k):
            prior = F.when(F.size(ends) == 0, F.lit(1.0)).otherwise(acc["best"])
            here = F.when(F.size(ends) == 0, F.lit(0.0)).otherwise(F.coalesce(F.get(ends, k), F.lit(0.0)))
            value = match(F.get("ev", k), want) * prior
            return F.struct(F.array_append(acc["out"], value).alias("out"), F.greatest(acc["best"], here).alias("best"))

        return F.aggregate(F.sequence(F.lit(0), F.size("ev") - 1), zero, step)["out"]

    ends = F.aggregate("want", F.array().cast("array<double>"), one_event)
    return j.select("pattern", "seq_id", F.array_max(ends).alias("best")).where("best > 0").groupBy("pattern").agg(F.sum("best").alias("es"), F.count(F.lit(1)).alias("support"))


def _pairwise(occ: DataFrame, patterns: list[P.Steps]) -> DataFrame:
    spark = occ.sparkSession
    items = sorted({i for s in patterns for _, i in s})
    ids = {x: k for k, x in enumerate(items)}
    packed = pack(occ, spark.createDataFrame(list(ids.items()), "item string, id int"))
    wanted = [[[ids[i] for i in e] for e in P.events_of(s)] for s in patterns]

    def run(batches):
        es, support, ops = np.zeros(len(wanted)), np.zeros(len(wanted), np.int64), np.zeros(len(wanted), np.int64)
        for b in batches:
            for sequence in b.column(0).to_pylist():
                by: dict[int, dict[int, float]] = {}
                for o in sequence:
                    by.setdefault(o["pos"], {})[o["item"]] = o["p"]
                events = [by[k] for k in sorted(by)]
                for k, w in enumerate(wanted):
                    best, n = pairwise_best(events, w)
                    es[k] += best
                    support[k] += best > 0
                    ops[k] += n
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(wanted))), pa.array(es), pa.array(support), pa.array(ops)], ["node", "es", "support", "ops"])

    names = spark.createDataFrame([(k, P.to_text(s)) for k, s in enumerate(patterns)], "node long, pattern string")
    sums = packed.select("events").mapInArrow(run, "node long, es double, support long, ops long").groupBy("node").agg(F.sum("es").alias("es"), F.sum("support").alias("support"), F.sum("ops").alias("ops"))
    return sums.join(names, "node").where("support > 0").select("pattern", "es", "support", "ops")


def pairwise_joins(occ: DataFrame, patterns: DataFrame, depth: int) -> DataFrame:
    """The quadratic baseline as range joins: every pattern on its own, each end against all later occurrences."""
    o = occ.select("seq_id", F.col("pos").cast("long").alias("pos"), "item", "p")
    s = patterns.select("pattern", F.posexplode(P.steps("pattern")).alias("k", "s")).select("pattern", "k", F.col("s.kind").alias("kind"), "s.item")
    size = patterns.select("pattern", P.length("pattern").alias("n"))
    level = o.join(F.broadcast(s.where("k = 0")), "item").select("pattern", "seq_id", "pos", F.col("p").alias("pr"))
    done = None
    for d in range(1, depth + 1):
        whole = level.join(F.broadcast(size.where(F.col("n") == d)), "pattern").groupBy("pattern", "seq_id").agg(F.max("pr").alias("best"))
        done = whole if done is None else done.unionByName(whole)
        if d < depth:
            step = F.broadcast(s.where(F.col("k") == d).select("pattern", "kind", "item"))
            left = level.join(step, "pattern").withColumnRenamed("pos", "end")
            later = (F.col("kind") == "S") & (F.col("pos") > F.col("end")) | (F.col("kind") == "I") & (F.col("pos") == F.col("end"))
            level = left.join(o, ["seq_id", "item"]).where(later).groupBy("pattern", "seq_id", "pos").agg(F.max(F.col("pr") * F.col("p")).alias("pr"))
    return done.groupBy("pattern").agg(F.sum("best").alias("es"), F.count(F.lit(1)).alias("support"))


def expected_support(occ: DataFrame, patterns: DataFrame, weights: DataFrame | None = None, engine: str = "arrow") -> DataFrame:
    """(pattern, support, es, seq_weight, wes) of the given patterns; those that never occur have zeros."""
    if engine not in ("arrow", "relational", "hof", "pairwise"):
        raise ValueError(f"no engine {engine!r}")
    given = patterns.select("pattern").distinct()
    if engine == "hof":
        found = _hof(occ, given)
    else:
        steps = [P.to_steps(r["pattern"]) for r in given.collect()]  # the caller's patterns, a tree that tasks can hold
        if not steps:
            found = given.select("pattern", F.lit(0.0).alias("es"), F.lit(0).cast("long").alias("support"))
        elif engine == "relational":
            found = _relational(occ, given, max(map(len, steps)))
        else:
            found = (_arrow if engine == "arrow" else _pairwise)(occ, steps)
    out = given.join(found, "pattern", "left").join(seq_weight(given, weights), "pattern")
    es = F.coalesce("es", F.lit(0.0))
    return out.select("pattern", F.coalesce("support", F.lit(0)).cast("long").alias("support"), es.alias("es"), "seq_weight", (es * F.col("seq_weight")).alias("wes"))


def max_pr_in_seq(occ: DataFrame, patterns: DataFrame) -> DataFrame:
    """(seq_id, pattern, best): the best match probability of each pattern in each sequence that has it."""
    given = [P.to_steps(r["pattern"]) for r in patterns.select("pattern").distinct().collect()]
    items = sorted({i for s in given for _, i in s})
    ids = {x: k for k, x in enumerate(items)}
    spark = occ.sparkSession
    packed = pack(occ, spark.createDataFrame(list(ids.items()), "item string, id int"))
    tree, nodes = tree_of(given, ids)
    children, wanted = tree.children(), {k for k, s in enumerate(nodes) if s in set(given)}
    names = [P.to_text(s) for s in nodes]

    def run(batches):
        for b in batches:
            seqs = b.column(0).to_numpy()
            for at, batch in batches_of(b.column(1)):
                got: list[tuple] = []

                def visit(k, state, at=at, got=got):
                    if k in wanted:
                        got.append((seqs[at + state.rows], [names[k]] * len(state.rows), state.best))

                walk(batch, tree, children, visit)
                if got:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([g[0] for g in got])), pa.array([x for g in got for x in g[1]]), pa.array(np.concatenate([g[2] for g in got]))], ["seq_id", "pattern", "best"])

    return packed.select("seq_id", "events").mapInArrow(run, "seq_id long, pattern string, best double")


def end_positions(occ: DataFrame, patterns: DataFrame) -> DataFrame:
    """(seq_id, pattern, pos, pr): every event where a pattern can end, with the best probability there."""
    depth = max((len(P.to_steps(r["pattern"])) for r in patterns.select("pattern").distinct().collect()), default=0)
    nodes = tree_nodes(patterns)
    rows = occ.select("seq_id", F.col("pos").cast("long").alias("pos"), "item", "p")
    level = rows.join(F.broadcast(nodes.where("depth = 1").select("node", "item")), "item").select("node", "seq_id", "pos", F.col("p").alias("pr"))
    out = level
    for d in range(2, depth + 1):
        level = _next_level(level, nodes.where(F.col("depth") == d).select("node", "parent", "kind", "item"), rows)
        out = out.unionByName(level)
    return out.join(F.broadcast(patterns.select(F.col("pattern").alias("node")).distinct()), "node", "left_semi").select("seq_id", F.col("node").alias("pattern"), "pos", "pr")


