"""The capped batch miner and its variants.

Level by level: a pass over the data gives, for every live node, the maximum, sum and count of each extension's best
probability. From these come the tight and the loose support cap at once. With a weight cap they bound the weighted
expected support of everything below, so what stays under the threshold is cut with all its descendants. Exact
supports follow in one scan for all candidates, or with verify="fused" from the next level's pass.

With prune="exact" and unequal weights a pattern is found through its lightest item (see `_by_lightest`).

The driver holds the candidates and never a sequence. A run takes one pass per pattern length and at most one more; a
level of more than `max_candidates` nodes takes a pass for every so many of them.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from probseq.config import SLACK, MiningParams
from probseq.functions import patterns as P
from probseq.operators.encode import Packed, dictionary, pack
from probseq.operators.engines import ROOT, ArrowEngine, RelationalEngine
from probseq.operators.kernel import Tree
from probseq.operators.measures import global_threshold
from probseq.operators.support import NODES as TREE_NODES
from probseq.operators.support import expected_support, scan_tree, tree_of

RESULT = "pattern string, length int, n_events int, support long, es double, seq_weight double, wes double"
NODES = "pattern string, parent string, depth int, kind string, item string, max_pr double, es_cap double, es_cap_loose double, w_cap double, wes_cap double, support long, es double, seq_weight double, wes double, frequent boolean"


@dataclass
class MiningRun:
    result: DataFrame
    candidates: DataFrame
    counters: list[dict]
    stats: dict
    threshold: float
    seconds: float
    rows: list[tuple] = field(default_factory=list)  # of `candidates`

    @property
    def n_candidates(self) -> int:
        return len(self.rows)

    @property
    def n_frequent(self) -> int:
        return sum(r[-1] for r in self.rows)


@dataclass
class _Node:
    steps: P.Steps
    parent: int
    max_pr: float
    es_cap: float
    loose: float
    w_cap: float
    sum_w: float
    max_w: float
    support: int = 0
    es: float | None = None


def live_extensions(cap: np.ndarray, weight: np.ndarray, own_max: float, threshold: float) -> tuple[np.ndarray, float]:
    """(which extensions stay, weight cap of the node): drop what cannot reach the threshold with the heaviest of what
    is still there, until nothing changes."""
    keep = np.ones(len(cap), bool)
    while True:
        top = max(own_max, float(weight[keep].max()) if keep.any() else 0.0)
        new = keep & (cap * top >= threshold * (1 - SLACK))
        if (new == keep).all():
            return keep, top
        keep = new


def mine_capped(occ: DataFrame, weights: DataFrame | None, params: MiningParams, threshold: float | None = None, packed: Packed | None = None) -> MiningRun:
    """All patterns whose weighted expected support reaches the threshold (given, or from `params`).

    Where `occ` is packed already, the search through lightest items takes it from there.
    """
    began, spark = time.time(), occ.sparkSession
    if packed is not None and _light(params):
        return _mine_packed(spark, packed, weights, params, threshold, began)
    items = dictionary(occ, weights).persist()  # one row per item: counts, weights and what level 1 needs
    f = "occ" if params.freq == "occurrences" else "seqs"
    head = items.agg(F.sum(F.col("weight") * F.col(f)).alias("wf"), F.sum(f).alias("f"), F.max("weight").alias("w")).first()
    n = occ.select("seq_id").distinct().count()
    wam, w_max = (head["wf"] / head["f"], head["w"]) if head["f"] else (0.0, 0.0)
    if threshold is None:
        threshold = global_threshold(n, wam, params.min_sup, params.wgt_fct)
    stats = {"n_seq": n, "wam": wam, "w_max": w_max, "min_wes": threshold}
    if n and threshold <= 0 and params.max_len is None:
        raise ValueError("a threshold of 0 keeps everything: give max_len")
    # items that no frequent pattern can hold, as their own cap fails even with the heaviest weight, never leave the scan
    value = F.col("sm") if params.support_cap == "tight" else F.col("mx") * F.col("seqs")
    ones = items.where(value * w_max >= threshold * (1 - SLACK))
    first = sorted(tuple(r) for r in ones.select("item", "weight", "mx", "sm", "seqs").collect())
    items.unpersist()
    names, weight_of = [r[0] for r in first], np.array([r[1] for r in first])
    if not names:
        empty = spark.createDataFrame([], RESULT)
        return MiningRun(empty, spark.createDataFrame([], NODES), [], stats, threshold, time.time() - began)
    ids = spark.createDataFrame([(name, k) for k, name in enumerate(names)], "item string, id int")
    if _light(params) and weight_of.min() < weight_of.max():
        kept = pack(occ, ids).persist(StorageLevel.MEMORY_AND_DISK)
        try:
            rows, counters = _by_lightest(kept, first, list(range(len(first))), params, threshold)
        finally:
            kept.unpersist()
        return _finished(spark, rows, counters, stats, threshold, began)
    engine = (ArrowEngine if params.engine == "arrow" else RelationalEngine)(occ, ids, params.i_ext == "cooccurring")
    nodes: list[_Node] = []
    counters, depth, live = [], 0, np.array([ROOT])
    w_global = w_max
    try:
        while len(live):
            level_began = time.time()
            tree = _tree(nodes, names)
            grows = params.max_len is None or depth < params.max_len
            before, tested = len(nodes), 0
            groups = [live[k : k + params.max_candidates] for k in range(0, len(live), params.max_candidates)]
            for group, passed in zip(groups, engine.level(tree, groups), strict=True):
                seen = Observation()
                heads = [(ROOT, 1.0)] if depth == 0 else [(int(k), nodes[k].max_pr) for k in group]
                pr = spark.createDataFrame(heads, "node long, max_pr double")
                cap = F.col("max_pr") * (F.col("sm") if params.support_cap == "tight" else F.col("mx") * F.col("ct"))
                kept = passed.join(F.broadcast(pr), "node").observe(seen, F.sum((F.col("kind") != "E").cast("long")).alias("tested"))
                kept = kept.where((F.col("kind") == "E") | (F.lit(grows) & (cap * w_global >= threshold * (1 - SLACK))))
                found = kept.select("node", "kind", "item", "mx", "sm", "ct").collect()  # candidates at most
                tested += (seen.get.get("tested") or 0) if grows else 0
                by_node: dict[int, list] = {}
                for r in found:
                    if r["kind"] == "E":
                        nodes[r["node"]].es, nodes[r["node"]].support = r["sm"], r["ct"]
                    else:
                        by_node.setdefault(r["node"], []).append(r)
                for k in group.tolist():
                    own = sorted(by_node.get(k, []), key=lambda r: (r["kind"] == "I", r["item"]))
                    node = nodes[k] if k != ROOT else _Node((), -1, 1.0, 0, 0, 0, 0.0, 0.0)
                    mx, sm, ct = (np.array([r[c] for r in own], float) for c in ("mx", "sm", "ct"))
                    w = weight_of[[r["item"] for r in own]] if own else np.zeros(0)
                    tight, loose = node.max_pr * sm, node.max_pr * mx * ct
                    bound = tight if params.support_cap == "tight" else loose
                    if params.weight_cap == "global":
                        keep, top = bound * w_global >= threshold * (1 - SLACK), w_global
                    else:
                        keep, top = live_extensions(bound, w, node.max_w, threshold)
                    if k != ROOT and params.prune == "exact" and (node.es or 0.0) * max(top, node.max_w) < threshold * (1 - SLACK):
                        keep = np.zeros(len(own), bool)
                    for i in np.flatnonzero(keep):
                        r = own[i]
                        steps = (*node.steps, (r["kind"], names[r["item"]]))
                        heavy = max(node.max_w, float(w[i]))
                        w_cap = w_global if params.weight_cap == "global" else max(heavy, top)
                        nodes.append(_Node(steps, k, float(node.max_pr * mx[i]), float(tight[i]), float(loose[i]), w_cap, node.sum_w + float(w[i]), heavy))
            live = np.arange(before, len(nodes))
            depth += 1
            counters.append({"level": depth, "tested": int(tested), "candidates": len(live), "seconds": time.time() - level_began})
        if params.verify == "final_scan" and nodes:
            texts = spark.createDataFrame([(P.to_text(x.steps),) for x in nodes], "pattern string")
            exact = {r["pattern"]: r for r in expected_support(occ, texts, None, params.engine).collect()}
            for x in nodes:
                r = exact[P.to_text(x.steps)]
                x.es, x.support = r["es"], r["support"]
    finally:
        engine.close()
    rows = []
    for x in nodes:
        mean = x.sum_w / len(x.steps)
        es = x.es or 0.0
        bound = (x.es_cap if params.support_cap == "tight" else x.loose) * x.w_cap
        rows.append((P.to_text(x.steps), P.to_text(x.steps[:-1]), len(x.steps), x.steps[-1][0], x.steps[-1][1], x.max_pr, x.es_cap, x.loose, x.w_cap, bound, int(x.support), es, mean, es * mean, bool(es * mean >= threshold * (1 - SLACK))))
    return _finished(spark, rows, counters, stats, threshold, began)


def _light(params: MiningParams) -> bool:
    return params.prune == "exact" and params.engine == "arrow" and params.verify == "fused"


def _mine_packed(spark, packed: Packed, weights: DataFrame | None, params: MiningParams, threshold: float | None, began: float) -> MiningRun:
    """As mine_capped through lightest items, with counts and sequences that are there already."""
    known = {} if weights is None else {r["item"]: r["weight"] for r in weights.select("item", "weight").collect() if r["weight"] is not None}
    first = [(x, known.get(x, 1.0), mx, sm, seqs) for x, _, seqs, mx, sm in packed.items]
    many = [occ if params.freq == "occurrences" else seqs for _, occ, seqs, _, _ in packed.items]
    wam = sum(r[1] * f for r, f in zip(first, many, strict=True)) / sum(many) if many else 0.0
    w_max = max((r[1] for r in first), default=0.0)
    if threshold is None:
        threshold = global_threshold(packed.n_seq, wam, params.min_sup, params.wgt_fct)
    stats = {"n_seq": packed.n_seq, "wam": wam, "w_max": w_max, "min_wes": threshold}
    if packed.n_seq and threshold <= 0 and params.max_len is None:
        raise ValueError("a threshold of 0 keeps everything: give max_len")
    tight = params.support_cap == "tight"
    alive = [k for k, r in enumerate(first) if (r[3] if tight else r[2] * r[4]) * w_max >= threshold * (1 - SLACK)]
    rows, counters = _by_lightest(packed.rows, first, alive, params, threshold, packed.names) if alive else ([], [])
    return _finished(spark, rows, counters, stats, threshold, began)


def _finished(spark, rows: list[tuple], counters: list[dict], stats: dict, threshold: float, began: float) -> MiningRun:
    for c in counters:
        c["frequent"] = sum(r[-1] for r in rows if r[2] == c["level"])
    good = [(r[0], r[2], r[0].count("("), r[10], r[11], r[12], r[13]) for r in rows if r[-1]]
    result = spark.createDataFrame(good, RESULT)
    return MiningRun(result, spark.createDataFrame(rows, NODES), counters, stats, threshold, time.time() - began, rows)


Events = tuple[tuple[int, ...], ...]


def _inserted(events: Events, x: int) -> set[Events]:
    """All patterns that have one more item x, in an event of its own or within one."""
    out = {(*events[:k], (x,), *events[k:]) for k in range(len(events) + 1)}
    return out | {(*events[:k], tuple(sorted((*e, x))), *events[k + 1 :]) for k, e in enumerate(events) if x not in e}


def _shorter(events: Events):
    """All patterns that lack one item, and that item."""
    for k, e in enumerate(events):
        for i in range(len(e)):
            rest = e[:i] + e[i + 1 :]
            yield ((*events[:k], rest, *events[k + 1 :]) if rest else events[:k] + events[k + 1 :]), e[i]


def _by_lightest(packed: DataFrame, first: list[tuple], alive: list[int], params: MiningParams, threshold: float, own: list[str] | None = None) -> tuple[list[tuple], list[dict]]:
    """(rows of NODES, counters) of a search that adds items from the heaviest to the lightest.

    A pattern without its lightest item occurs at least as often and has at least its mean weight, so it is frequent if the
    pattern is. All frequent patterns are thus found by putting an item no heavier than the lightest anywhere into a
    frequent one, and a level without frequent patterns ends the search. Of the candidates only those are scanned whose
    weight makes the threshold with the least support known of their parts, or with the sum over sequences of what a part
    and the item that it lacks reach there (`beside`, of the scan before). `first` has every item of the packed rows,
    `alive` are those that a frequent pattern can hold, `own` the names by id of rows in blocks.
    """
    names, weight = [r[0] for r in first], [r[1] for r in first]
    best, single = [r[2] for r in first], [r[3] for r in first]
    low = threshold * (1 - SLACK)
    seed = threshold * (1 - 2 * SLACK)  # a part's sum may round to just under what its pattern reaches
    rows, counters, depth = [], [], 0
    known: dict[Events, float] = {}  # supports of the level before, or what bounds them
    beside: dict[Events, list[float]] = {}  # of patterns of the level before: bounds by the item that is added
    seeds: list[tuple[Events, float, float]] = []  # frequent patterns of the level before, their support and weight
    while True:
        began, depth = time.time(), depth + 1
        bound: dict[Events, float] = {}
        tested: set[Events] = set()
        if depth == 1:
            bound = {((k,),): single[k] for k in alive}
            tested = set(bound)
        elif params.max_len is None or depth <= params.max_len:
            for events, es, total in seeds:
                least, reach = min(weight[i] for e in events for i in e), beside.get(events)
                for x in alive:
                    w = weight[x]
                    mean, most = (total + w) / depth, min(es, single[x])
                    if reach is not None:
                        most = min(most, reach[x])
                    if w > least or most * mean < low:
                        continue
                    for y in _inserted(events, x) - tested:
                        tested.add(y)
                        here = most
                        for z, lacking in _shorter(y):
                            here = min(here, known.get(z, es), beside[z][lacking] if z in beside else es)
                        bound[y] = here
        scanned = {}
        for y, most in bound.items():
            total = sum(weight[i] for e in y for i in e)
            if depth == 1 or most * total / depth >= low:
                scanned[y] = total
        if depth == 1:
            exact = {((k,),): (first[k][3], first[k][4]) for k in alive}
        else:
            deepest = params.max_len is not None and depth >= params.max_len
            exact, beside = _scan(packed, list(scanned), depth, params.max_candidates, own, 0 if deepest else len(first))
        known = bound | {y: exact.get(y, (0.0, 0))[0] for y in scanned}
        seeds = []
        for y, total in scanned.items():
            es, support = exact.get(y, (0.0, 0))
            steps = tuple(("I" if i else "S", names[x]) for e in y for i, x in enumerate(e))
            mean, top = total / depth, float(np.prod([best[x] for e in y for x in e]))
            rows.append((P.to_text(steps), P.to_text(steps[:-1]), depth, *steps[-1], top, bound[y], bound[y], mean, bound[y] * mean, int(support), es, mean, es * mean, bool(support and es * mean >= low)))
            if support and es * mean >= seed:
                seeds.append((y, es, total))
        counters.append({"level": depth, "tested": len(tested), "candidates": len(scanned), "seconds": time.time() - began})
        if not scanned:
            break
    return rows, counters


BESIDE = 64, 1 << 22  # items, and items x patterns, up to which a scan sums what patterns reach with every item


def _scan(packed: DataFrame, patterns: list[Events], depth: int, most: int, own: list[str] | None = None, items: int = 0) -> tuple[dict[Events, tuple[float, int]], dict[Events, list[float]]]:
    """(expected support, sequences) of patterns that occur, in passes whose trees tasks can hold; and, for not too many of the
    `items`, the sums over sequences of a pattern's and an item's best probabilities."""
    out: dict[Events, tuple[float, int]] = {}
    beside: dict[Events, list[float]] = {}
    if not patterns:
        return out, beside
    if items > BESIDE[0] or items * len(patterns) > BESIDE[1]:
        items = 0
    spelt = sorted(tuple(("I" if i else "S", x) for e in y for i, x in enumerate(e)) for y in patterns)
    cuts, size, before = [0], 0, ()
    for at, s in enumerate(spelt):
        same = next((k for k, (a, b) in enumerate(zip(before, s, strict=False)) if a != b), min(len(before), depth))
        size += depth - same
        if at > cuts[-1] and (at - cuts[-1] >= most or size > TREE_NODES):
            cuts.append(at)
            size = depth
        before = s
    for a, b in zip(cuts, [*cuts[1:], len(spelt)], strict=True):
        tree, nodes = tree_of(spelt[a:b], {x: x for s in spelt[a:b] for _, x in s})
        found = scan_tree(packed, tree, own, items).toArrow()
        sums = np.column_stack([found.column(f"b{i}").to_numpy() for i in range(items)]) * (1 + SLACK) if items else None
        for at, (k, es, support) in enumerate(zip(*(found.column(c).to_pylist() for c in ("node", "es", "support")), strict=True)):
            if len(nodes[k]) == depth:
                y = tuple(tuple(e) for e in P.events_of(nodes[k]))
                out[y] = (es, support)
                if items:
                    beside[y] = sums[at].tolist()
    return out, beside


def _tree(nodes: list[_Node], names: list[str]) -> Tree:
    index = {name: k for k, name in enumerate(names)}
    return Tree(
        np.array([x.parent for x in nodes], np.int64),
        np.array([x.steps[-1][0] for x in nodes] or [], "S1"),
        np.array([index[x.steps[-1][1]] for x in nodes], np.int64),
    )
