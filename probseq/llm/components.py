"""Connected components over a table of links, with nothing on the driver but a count per round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import by_sort, discard, settle


FILE_ROWS = 1_000_000


def components(links: DataFrame) -> DataFrame:
    """(node, root): the smallest node that each linked node can reach; `links` has long columns a and b.

    Every round hangs each node's larger neighbours below its smallest one, then each node and its smaller neighbours
    below the smallest of these, until no edge changes. Edges stay at most as many as links, and long chains halve. The
    result is a settled table, the only one that stays.
    """
    edges = settle(links.where("a <> b").select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).distinct(), "edges")
    mark = lambda d: d.agg(F.count(F.lit(1)), F.sum(F.xxhash64("v", "u").cast("decimal(38,0)"))).first()
    last = mark(edges)
    while True:
        # large step: all neighbours of a node that exceed it go below its smallest neighbour or itself
        both = edges.select("v", "u").union(edges.select(F.col("u").alias("v"), F.col("v").alias("u")))
        least = both.groupBy("v").agg(F.least(F.min("u"), F.col("v")).alias("m"))
        large = by_sort(both.where("u > v"), least, "v").select(F.col("u").alias("v"), F.col("m").alias("u")).where("v <> u").distinct()
        # small step: a node and its smaller neighbours go below the smallest of these
        low = large.groupBy("v").agg(F.min("u").alias("m"))
        joined = by_sort(large, low, "v")
        small = joined.select(F.col("u").alias("v"), F.col("m").alias("u")).union(low.select("v", F.col("m").alias("u"))).where("v <> u").distinct()
        # edges never grow in number, so their count says how many files they need
        before, edges = edges, settle(small.coalesce(max(1, -(-last[0] // FILE_ROWS))), "edges")
        discard(before)
        now = mark(edges)
        if now == last:
            break
        last = now
    nodes = edges.select(F.col("v").alias("node"), F.col("u").alias("root"))
    out = settle(nodes.union(edges.select(F.col("u").alias("node"), F.col("u").alias("root"))).distinct(), "components")
    discard(edges)
    return out
