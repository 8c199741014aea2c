"""The worked example: six sequences and seven weights."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from probseq.sources.notation import occurrences

# The example database and its weights.
SEQUENCES = [
    (1, "(a:0.9, c:0.6)(a:0.7)(b:0.3)(d:0.7)"),
    (2, "(a:0.6, c:0.4)(a:0.5)(a:0.4, b:0.3)"),
    (3, "(a:0.3)(a:0.2, b:0.2)(a:0.4, b:0.3, g:0.5)"),
    (4, "(a:0.1, c:0.1)(a:0.3, b:0.1, c:0.4)"),
    (5, "(d:0.1)(a:0.4)(d:0.1)(a:0.5, c:0.6)"),
    (6, "(b:0.3)(b:0.4)(a:0.1)(a:0.1, b:0.2)"),
]
WEIGHTS = [("a", 0.8), ("b", 1.0), ("c", 0.9), ("d", 0.9), ("e", 0.7), ("f", 0.9), ("g", 0.8)]
TREE_SEQUENCE = "(a:0.8)(b:0.7)(a:0.9, b:0.6)(c:0.3)(d:0.9)"
TREE_PATTERNS = ["<(a)>", "<(b)>", "<(a b)>", "<(c)>", "<(b)(c)>", "<(d)>", "<(c d)>", "<(c)(d)>"]


def toy_occurrences(spark: SparkSession) -> DataFrame:
    return occurrences(spark.createDataFrame(SEQUENCES, "seq_id long, sequence string"))


def toy_weights(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(WEIGHTS, "item string, weight double")
