"""Aggregates over occurrences for one given pattern."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from probseq.functions import patterns as P
from probseq.operators.kernel import batches_of, walk
from probseq.operators.support import tree_of


def expected_support_by(occ: DataFrame, pattern: str, *groups: Column) -> DataFrame:
    """(groups, support, es) of one pattern: many packed sequences at once in Arrow batches, then one small aggregate."""
    steps = P.to_steps(pattern)
    ids = {x: k for k, x in enumerate(sorted({i for _, i in steps}))}
    tree, nodes = tree_of([steps], ids)
    children, wanted = tree.children(), len(nodes) - 1
    named = occ.select(*groups, "seq_id", "pos", "item", "p")
    keys = named.columns[: len(groups)]
    # other items only tell that a sequence belongs to a group
    known = F.lit(None).cast("int")
    for x, k in ids.items():
        known = F.when(F.col("item") == x, k).otherwise(known)
    e = F.struct(F.col("pos").cast("int").alias("pos"), known.alias("item"), "p")
    packed = named.groupBy(*keys, "seq_id").agg(F.array_sort(F.collect_list(F.when(known.isNotNull(), e))).alias("events"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            events = b.column(len(keys))
            best = np.zeros(b.num_rows)

            def visit(k, state, best=best):
                if k == wanted:
                    best[at + state.rows] = state.best

            for at, batch in batches_of(events):
                walk(batch, tree, children, visit)
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keys)], pa.array(best)], [*keys, "best"])

    schema = StructType([*named.select(*keys).schema.fields, StructField("best", DoubleType())])
    per = packed.select(*keys, "events").mapInArrow(run, schema)
    return per.groupBy(*keys).agg(F.count(F.when(F.col("best") > 0, 1)).alias("support"), F.sum("best").alias("es"))
