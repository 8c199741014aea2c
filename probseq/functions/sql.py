"""SQL surface: table functions over packed sequences, views, and pattern functions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from probseq.functions import patterns as P


@udtf(returnType="pos int, pr double")
class PatternEnds:
    """pattern_ends(events, pattern): where a pattern can end in a sequence, and with what probability.

    `events` is array<struct<pos int, items map<string, double>>>.
    """

    def eval(self, events: list, pattern: str) -> Iterator[tuple]:
        ends: list[float] | None = None
        rows = events or []
        for want in P.events_of(P.to_steps(pattern or "")):
            best, new = (1.0 if ends is None else 0.0), []
            for k, e in enumerate(rows):
                here = 1.0
                for i in want:
                    here *= e["items"].get(i, 0.0)
                new.append(here * best)
                if ends is not None:
                    best = max(best, ends[k])
            ends = new
        for e, pr in zip(rows, ends or [], strict=False):
            if pr > 0:
                yield e["pos"], pr


@udtf(returnType="depth int, kind string, item string, prefix string")
class PatternPrefixes:
    """pattern_prefixes(pattern): the nodes on a pattern's path in the tree."""

    def eval(self, pattern: str) -> Iterator[tuple]:
        steps = P.to_steps(pattern or "")
        for k in range(1, len(steps) + 1):
            yield k, steps[k - 1][0], steps[k - 1][1], P.to_text(steps[:k])


def register_all(spark: SparkSession, occ: DataFrame | None = None, weights: DataFrame | None = None, patterns: DataFrame | None = None, state: DataFrame | None = None) -> None:
    """Functions, and views occurrences, weights, patterns and state of what is given."""
    P.register(spark)
    spark.udtf.register("pattern_ends", PatternEnds)
    spark.udtf.register("pattern_prefixes", PatternPrefixes)
    for name, df in (("occurrences", occ), ("weights", weights), ("patterns", patterns), ("state", state)):
        if df is not None:
            df.createOrReplaceTempView(name)
