"""Near-duplicate vectors within a label: int8 tile products with error bounds, then doubles where these leave doubt.

A unit vector x is kept as s * q + e with int8 q; |x.y - s_x s_y q_x.q_y| <= |s_x q_x| |e_y| + |e_x| |s_y q_y| + |e_x| |e_y|,
so a tile of integer products decides almost all pairs, and only those whose interval contains the threshold are
computed again in double precision. Integer products up to 2^24 are exact in float32, whose matrix product is fast.

Equal vectors of a label are one class first. Classes are cut into blocks by their nearest of a few
pivots; two blocks meet only if the angle between their centres leaves room for a link (triangle inequality, exact). A tile yields, per vector, how many it links with and one edge to the least member of its part of the tile:
rows grow with vectors, not with pairs. Vectors that are null, zero, or hold null or non-finite values, and those with a
null label, link with nothing. Vectors of different lengths link with nothing. Repeated (vec_id, label, vector) rows are one vector.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import by_sort, discard, numbered, settle
from probseq.llm.components import components

BLOCK = 1024
PIVOTS = 4


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Unit rows -> int8 codes, scales, norm of the coded part and norm of the error, both rounded up."""
    scale = np.abs(x).max(axis=1) / 127
    q = np.rint(x / scale[:, None]).astype(np.int8)
    coded = scale[:, None] * q
    up = 1 + 1e-12
    return q, scale, np.linalg.norm(coded, axis=1) * up, np.linalg.norm(x - coded, axis=1) * up + 1e-15


def unit(rows: np.ndarray) -> np.ndarray:
    """Rows scaled to length 1 in doubles; scaling by the largest part first keeps extreme values finite."""
    x = rows / np.abs(rows).max(axis=1)[:, None]
    return x / np.linalg.norm(x, axis=1)[:, None]


def tile_links(a: np.ndarray, b: np.ndarray, least: float) -> np.ndarray:
    """Pairs (i, j) of unit rows with a_i . b_j >= least."""
    qa, sa, ca, ea = quantise(a)
    qb, sb, cb, eb = quantise(b)
    exact = np.float32 if a.shape[1] * 127 * 127 < 1 << 24 else np.float64
    rough = (qa.astype(exact) @ qb.T.astype(exact)).astype(np.float64) * sa[:, None] * sb
    bound = ca[:, None] * eb + ea[:, None] * cb + ea[:, None] * eb + 1e-12
    sure = rough - bound >= least
    i, j = np.nonzero((rough + bound >= least) & ~sure)
    for k in range(0, len(i), 65536):
        p, q = i[k : k + 65536], j[k : k + 65536]
        sure[p, q] = np.einsum("ij,ij->i", a[p], b[q]) >= least
    return np.argwhere(sure)


def roots(n: int, pairs: np.ndarray) -> np.ndarray:
    """The least member of each of n nodes' part, by label spreading over pairs."""
    root = np.arange(n)
    while len(pairs):
        low = np.minimum(root[pairs[:, 0]], root[pairs[:, 1]])
        new = root.copy()
        np.minimum.at(new, pairs[:, 0], low)
        np.minimum.at(new, pairs[:, 1], low)
        new = new[new]
        if (new == root).all():
            break
        root = new
    return root


def link(vectors: DataFrame, least: float = 0.98, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", block: int = BLOCK) -> DataFrame:
    """(id, n_links, component_id, kept) of every vector."""
    spark = vectors.sparkSession
    stored = vectors.schema[vector].dataType.simpleString()  # vectors travel in the width they came in
    reach = math.acos(min(1.0, least)) + 1e-7
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(label).alias("label"), F.col(vector).cast("array<double>").alias("v")).distinct()
    good = F.col("label").isNotNull() & F.col("id").isNotNull() & (F.size("v") > 0) & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    sane = rows.where(F.coalesce(good, F.lit(False)))
    # the direction alone counts, so classes are of equal stored vectors
    classed = sane.select("id", "label", "v", F.xxhash64("label", "v").alias("h"))
    classes = classed.groupBy("h", "label", "v").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("many"))
    members = by_sort(classed.select("id", "label", "v"), classes, ["label", "v"]).select("id", "rep", "many")
    # a bounded sample of vectors serves as pivots
    picked = [np.array(r["v"]) for r in sane.select("v").orderBy(F.xxhash64("v"), "v").limit(PIVOTS).collect()]

    def near_pivot(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = np.diff(b.column(0).offsets.to_numpy())
            flat = b.column(0).flatten().to_numpy(zero_copy_only=False)
            own, turn = np.zeros(len(n), np.int32), np.zeros(len(n))
            for d in np.unique(n):
                at = np.flatnonzero(n == d)
                x = unit(flat[np.repeat(n == d, n)].reshape(-1, d))
                mine = [k for k, p in enumerate(picked) if len(p) == d]
                if mine:
                    angle = np.arccos(np.clip(x @ unit(np.array([picked[k] for k in mine])).T, -1, 1))
                    best = angle.argmin(axis=1)
                    own[at], turn[at] = np.array(mine)[best], angle[np.arange(len(at)), best]
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(b.num_columns)), pa.array(own), pa.array(turn)], [*b.schema.names, "pivot", "turn"])

    spread = classes.select("v", "label", "rep", "many").mapInArrow(near_pivot, f"v array<double>, label {vectors.schema[label].dataType.simpleString()}, rep long, many long, pivot int, turn double")
    # blocks: vectors of a label, length and nearest pivot; a block is what a tile multiplies, so it must not be small
    keyed = spread.withColumn("dim", F.size("v"))
    ranked = numbered(keyed, ["label", "dim", "pivot"], F.col("rep"), [F.col("rep")], "rank")
    blocked = settle(ranked.withColumn("part", F.floor(F.col("rank") / block).cast("int")), "vector-blocks")
    packed = settle(
        blocked.groupBy("label", "dim", "pivot", "part").agg(F.sort_array(F.collect_list(F.struct("rep", "many", F.col("v").cast(stored).alias("v")))).alias("rows")).withColumn("block", F.xxhash64("label", "dim", "pivot", "part")),
        "vector-tiles",
    )
    discard(blocked)

    def summary(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            centre, wide = [], []
            for rows_ in b.column(1).to_pylist():
                x = unit(np.array([r["v"] for r in rows_]))
                c = x.mean(axis=0)
                c = c / np.linalg.norm(c) if np.linalg.norm(c) > 1e-9 else x[0]
                centre.append(c)
                wide.append(float(np.arccos(np.clip(x @ c, -1, 1)).max()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(centre, pa.list_(pa.float64())), pa.array(wide, pa.float64())], ["block", "centre", "wide"])

    heads = packed.select("block", "rows").mapInArrow(summary, "block long, centre array<double>, wide double")
    heads = settle(packed.select("block", "label", "dim").join(heads, "block"), "vector-heads")
    x, y = heads.alias("x"), heads.alias("y")
    dot = F.aggregate(F.zip_with("x.centre", "y.centre", lambda p, q: p * q), F.lit(0.0), lambda s, p: s + p)
    apart = F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), dot)))
    meet = (F.col("x.label") == F.col("y.label")) & (F.col("x.dim") == F.col("y.dim")) & (F.col("x.block") <= F.col("y.block"))
    tiles = x.join(y, meet).where(apart <= F.col("x.wide") + F.col("y.wide") + F.lit(reach + 1e-6)).select(F.col("x.block").alias("p"), F.col("y.block").alias("q"))
    left = packed.select(F.col("block").alias("p"), F.col("rows").alias("left"))
    right = packed.select(F.col("block").alias("q"), F.col("rows").alias("right"))
    work = by_sort(by_sort(tiles, left, "p"), right, "q").select("p", "q", "left", "right").repartition("p", "q")

    def products(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def columns(a: pa.ListArray):
            f = a.flatten()
            v = f.field("v")
            return f.field("rep").to_numpy(), f.field("many").to_numpy(), v.flatten().to_numpy().astype(np.float64).reshape(len(f), -1)

        for batch in batches:
            for i in range(batch.num_rows):
                one = batch.slice(i, 1)
                ra, ma, va = columns(one.column(2))
                own = one.column(0)[0] == one.column(1)[0]
                rb, mb, vb = (ra, ma, va) if own else columns(one.column(3))
                pairs = tile_links(unit(va), unit(vb), least)
                if own:
                    pairs = pairs[pairs[:, 0] != pairs[:, 1]]
                    ids, n = ra, np.bincount(pairs[:, 0], ma[pairs[:, 1]], len(ra))
                    root = roots(len(ra), pairs)
                else:
                    ids = np.concatenate([ra, rb])
                    n = np.concatenate([np.bincount(pairs[:, 0], mb[pairs[:, 1]], len(ra)), np.bincount(pairs[:, 1], ma[pairs[:, 0]], len(rb))])
                    root = roots(len(ids), pairs + [0, len(ra)])
                hit = n > 0
                yield pa.RecordBatch.from_arrays([pa.array(ids[hit]), pa.array(n[hit].astype(np.int64)), pa.array(ids[root[hit]])], ["rep", "n", "to"])

    found = settle(work.mapInArrow(products, "rep long, n long, to long"), "vector-links")
    discard(heads, packed)
    counts = found.groupBy("rep").agg(F.sum("n").alias("n"))
    whole = components(found.select(F.col("rep").alias("a"), F.col("to").alias("b")))
    out = by_sort(by_sort(members, counts, "rep", "left"), whole, F.col("rep") == F.col("node"), "left")
    linked = out.select(F.col("id"), (F.coalesce("n", F.lit(0)) + F.col("many") - 1).cast("long").alias("n_links"), F.coalesce("root", "rep").alias("component_id"))
    # every id once: an id with several vectors has all their links
    merged = linked.groupBy(F.col("id").alias("own")).agg(F.sum("n_links").alias("n_links"), F.min("component_id").alias("least"))
    alone = rows.select("id").distinct().join(merged, F.col("id").eqNullSafe(F.col("own")), "left")
    alone = alone.select("id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("least", "id").alias("component_id"))
    return alone.select(F.col("id").alias(id_col), "n_links", "component_id", F.col("id").eqNullSafe(F.col("component_id")).alias("kept"))
