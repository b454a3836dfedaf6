"""What a physical plan does: exchanges, broadcasts, pushed filters, Python stages, and things that must not occur."""

from __future__ import annotations

import contextlib
import io
import re

from pyspark.sql import DataFrame


def text_of(df: DataFrame) -> str:
    with contextlib.redirect_stdout(io.StringIO()) as out:
        df.explain("formatted")
    return out.getvalue()


def nodes(df: DataFrame) -> list[str]:
    return re.findall(r"^\(\d+\) (\w+)", text_of(df), re.M)


def has_cartesian(df: DataFrame) -> bool:
    return any(n in ("CartesianProduct",) for n in nodes(df))


def single_partition(df: DataFrame) -> bool:
    return "SinglePartition" in text_of(df)


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]*)\]", text_of(df))


def read_schema(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: (struct<[^\n]*>)", text_of(df))


def uses_python(df: DataFrame) -> bool:
    return any(re.search("Python|Pandas|Arrow", n) for n in nodes(df))
