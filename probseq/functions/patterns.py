"""Patterns as text, as steps and as nested arrays, in Python and as Spark expressions.

Text: `<(a c)(b)>`, items of an event sorted and separated by a blank. Steps: a tuple of (kind, item) where kind S opens
an event and I adds to the last one.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

Steps = tuple[tuple[str, str], ...]
_event = re.compile(r"\(([^)]*)\)")


def to_text(steps: Steps) -> str:
    out = ""
    for kind, item in steps:
        out += f")({item}" if kind == "S" else f" {item}"
    return f"<{out[1:]})>" if out else "<>"


def to_steps(text: str) -> Steps:
    return tuple((("S", "I")[i > 0], item) for event in _event.findall(text) for i, item in enumerate(event.split(" ")))


def extend(steps: Steps, kind: str, item: str) -> Steps:
    """An s- or i-extension; an i-extension needs an item after the last one, so that every pattern has one spelling."""
    if kind not in "SI":
        raise ValueError("kind must be S or I")
    if kind == "I" and (not steps or item <= steps[-1][1]):
        raise ValueError("an i-extension adds a later item to an event")
    return (*steps, (kind, item))


def events_of(steps: Steps) -> list[list[str]]:
    out: list[list[str]] = []
    for kind, item in steps:
        if kind == "S":
            out.append([])
        out[-1].append(item)
    return out


def contains(whole: list, part: list) -> bool:
    """Whether `part` is a sub-sequence of `whole`: each of its events lies in a later event than the one before."""
    at = 0
    for event in part:
        while at < len(whole) and not set(event) <= set(whole[at]):
            at += 1
        if at == len(whole):
            return False
        at += 1
    return True


def events(pattern: Column | str) -> Column:
    """array<array<string>> of a pattern text."""
    found = F.regexp_extract_all(pattern, F.lit(r"\(([^)]*)\)"), F.lit(1))
    return F.transform(found, lambda e: F.split(e, " "))


def length(pattern: Column | str) -> Column:
    """Number of items."""
    return F.size(F.flatten(events(pattern)))


def n_events(pattern: Column | str) -> Column:
    return F.size(events(pattern))


def steps(pattern: Column | str) -> Column:
    """array<struct<kind, item>> of a pattern text."""
    each = F.transform(events(pattern), lambda e: F.transform(e, lambda x, i: F.struct(F.when(i == 0, F.lit("S")).otherwise(F.lit("I")).alias("kind"), x.alias("item"))))
    return F.flatten(each)


def text(nested: Column | str) -> Column:
    """Pattern text of array<array<string>>."""
    inner = F.transform(nested, lambda e: F.concat(F.lit("("), F.array_join(F.array_sort(e), " "), F.lit(")")))
    return F.concat(F.lit("<"), F.array_join(inner, ""), F.lit(">"))


def has(whole: Column | str, part: Column | str) -> Column:
    """Containment of nested arrays as one fold: how many events of `part` are matched after each event of `whole`."""
    part = F.col(part) if isinstance(part, str) else part
    step = lambda n, e: F.when((n < F.size(part)) & (F.size(F.array_except(F.coalesce(F.get(part, n), F.array()), e)) == 0), n + 1).otherwise(n)
    return F.aggregate(whole, F.lit(0), step) == F.size(part)


def register(spark: SparkSession) -> None:
    """SQL functions over pattern texts."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pattern_events(p STRING) RETURNS ARRAY<ARRAY<STRING>> RETURN transform(regexp_extract_all(p, '\\\\(([^)]*)\\\\)', 1), e -> split(e, ' '))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pattern_length(p STRING) RETURNS INT RETURN size(flatten(transform(regexp_extract_all(p, '\\\\(([^)]*)\\\\)', 1), e -> split(e, ' '))))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pattern_text(e ARRAY<ARRAY<STRING>>) RETURNS STRING RETURN concat('<', array_join(transform(e, x -> concat('(', array_join(array_sort(x), ' '), ')')), ''), '>')")
