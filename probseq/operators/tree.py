"""The pattern tree as a table: built from patterns, merged by path, listed and pruned.

A node is the text of its pattern, so trees of several sources meet by equal text, and neither tree has to fit a driver.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.config import SLACK
from probseq.operators.support import tree_nodes


@dataclass(frozen=True)
class PatternTree:
    """nodes: (node, parent, depth, kind, item, value, sources); `value` is null at nodes that are only on the way to others."""

    nodes: DataFrame

    @staticmethod
    def from_patterns(patterns: DataFrame, value: str = "wes") -> PatternTree:
        """The tree of `patterns` (pattern, value), prefixes shared."""
        own = patterns.groupBy(F.col("pattern").alias("node")).agg(F.max(value).cast("double").alias("value"))
        return PatternTree(tree_nodes(patterns.select("pattern").distinct()).join(own, "node", "left").withColumn("sources", F.lit(1)))

    def to_df(self) -> DataFrame:
        return self.nodes

    def merge(self, other: PatternTree) -> PatternTree:
        """Both trees in one: equal paths become one path, values are added, and `sources` says how many trees had a node."""
        both = self.nodes.unionByName(other.nodes)
        return PatternTree(both.groupBy("node", "parent", "depth", "kind", "item").agg(F.sum("value").alias("value"), F.sum("sources").cast("int").alias("sources")))

    def patterns(self) -> DataFrame:
        """(pattern, value) of the nodes that carry one."""
        return self.nodes.where("value is not null").select(F.col("node").alias("pattern"), "value")

    def select(self, threshold: float) -> DataFrame:
        """(pattern, value) of the nodes that reach the threshold."""
        return self.patterns().where(F.col("value") >= threshold * (1 - SLACK))

    def prune(self, threshold: float) -> PatternTree:
        """What reaches the threshold, and inner nodes that still lead to such; everything else goes."""
        kept = self.select(threshold)
        needed = tree_nodes(kept.select("pattern")).select("node")
        inner = F.when(F.col("value") >= threshold * (1 - SLACK), F.col("value"))
        return PatternTree(self.nodes.join(needed, "node", "left_semi").withColumn("value", inner))
