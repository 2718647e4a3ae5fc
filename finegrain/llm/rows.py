"""Rows carried whole beside an operator's own columns, so that no name of the caller's can clash with one of ours."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def quoted(name: str) -> str:
    """A column name as an expression, dots and all."""
    return "`" + name.replace("`", "``") + "`"


def column(name: str) -> Column:
    return F.col(quoted(name))


def packed(docs: DataFrame, **own: Column) -> DataFrame:
    """``row`` (all columns as one struct) and ``own`` columns."""
    return docs.select(F.struct(*map(column, docs.columns)).alias("row"), *(c.alias(name) for name, c in own.items()))


def unpacked(rows: DataFrame, names: list[str], *own: str, row: str = "row") -> DataFrame:
    """The caller's columns again, then ``own`` ones."""
    return rows.select(*(F.col(row).getField(name).alias(name) for name in names), *own)
