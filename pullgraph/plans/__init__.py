"""Looking at physical plans: what is pushed down, read, shuffled and broadcast."""

from __future__ import annotations

import contextlib
import io
import re
from collections import Counter

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    """The formatted plan as text."""
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def operators(df: DataFrame) -> Counter:
    """How often each operator stands in the plan."""
    return Counter(m[1].strip() for m in re.finditer(r"^\(\d+\) ([A-Za-z]+(?: [a-z]+)?)", physical(df), re.MULTILINE))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[(.*?)\]", physical(df))


def read_columns(df: DataFrame) -> list[set[str]]:
    """Columns that each scan reads."""
    return [set(re.findall(r"(\w+):", m)) for m in re.findall(r"ReadSchema: struct<(.*)>", physical(df))]


def forbid(df: DataFrame, *names: str) -> DataFrame:
    """df itself, or ValueError if its plan has one of the named operators."""
    found = [n for n in operators(df) if any(n.startswith(x) for x in names)]
    if found:
        raise ValueError(f"plan has {found}")
    return df
