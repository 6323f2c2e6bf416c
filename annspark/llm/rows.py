"""Rows packed in one struct column, so that no column name of a table can clash with an operator's own."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DataType, MapType, StructType


def _has_map(kind: DataType) -> bool:
    if isinstance(kind, StructType):
        return any(_has_map(f.dataType) for f in kind.fields)
    return isinstance(kind, MapType) or isinstance(kind, ArrayType) and _has_map(kind.elementType)


def column(df: DataFrame, name: str) -> Column:
    """A column by its plain name, dots and all."""
    return df[f"`{name}`"]


def row_hash(df: DataFrame) -> Column:
    """A hash of a whole row."""
    return F.xxhash64(*[F.to_json(F.struct(column(df, f.name))) if _has_map(f.dataType) else column(df, f.name) for f in df.schema.fields])


def packed(df: DataFrame) -> Column:
    """The whole row as the column ``row``."""
    return F.struct(*[column(df, c) for c in df.columns]).alias("row")


def unpacked(df: DataFrame, columns: list[str], renewed: dict[str, Column] | None = None) -> list[Column]:
    """The columns of the packed ``row``, with those of ``renewed`` in place of the old ones."""
    renewed = renewed or {}
    return [renewed[c].alias(c) if c in renewed else df["row"].getField(c).alias(c) for c in columns]
