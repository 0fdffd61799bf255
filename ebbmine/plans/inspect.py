"""What a plan does, as tests and reviews want to know it."""

from __future__ import annotations

from contextlib import redirect_stdout
from io import StringIO

from pyspark.sql import DataFrame


def formatted(df: DataFrame) -> str:
    out = StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def has(df: DataFrame, *nodes: str) -> bool:
    text = formatted(df)
    return all(x in text for x in nodes)
