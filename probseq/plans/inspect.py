"""Plans as text, and what tests ask of them."""

from __future__ import annotations

import re
from contextlib import redirect_stdout
from io import StringIO

from pyspark.sql import DataFrame


def explained(df: DataFrame) -> str:
    out = StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def shuffles(df: DataFrame) -> int:
    return len(re.findall(r"^\(\d+\) Exchange", explained(df), re.M))


def has_cartesian(df: DataFrame) -> bool:
    return "CartesianProduct" in explained(df)


def read_columns(df: DataFrame) -> list[str]:
    """ReadSchema of every file scan."""
    return re.findall(r"ReadSchema: (struct<[^\n]*)", explained(df))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: (\[[^\n]*\])", explained(df))
