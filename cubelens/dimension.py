"""Dimensions and measures: what an analyst declares about a table."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class DimensionSpec:
    """An ordered axis: sort keys (SQL expressions, ``desc`` allowed behind one), the first of them its label.

    Later keys order the rows of a frequent first value (secondary attribute). The same
    columns may appear in several dimensions with different orders.
    """

    name: str
    keys: tuple[str, ...]

    @property
    def rank(self) -> str:
        return f"rk_{self.name}"

    @property
    def bin(self) -> str:
        return f"b_{self.name}"

    def order(self) -> list[Column]:
        """Sort keys for Spark, nulls first."""
        out = []
        for k in self.keys:
            down = k.endswith(" desc")
            c = F.expr(k.removesuffix(" desc"))
            out.append(c.desc_nulls_first() if down else c.asc_nulls_first())
        return out

    def label(self) -> Column:
        return F.expr(self.keys[0].removesuffix(" desc"))

    def order_sql(self) -> str:
        return ", ".join(f"{k.removesuffix(' desc')} {'DESC' if k.endswith(' desc') else 'ASC'} NULLS FIRST" for k in self.keys)


@dataclass(frozen=True)
class MeasureSpec:
    """An additive measure: the sum of a SQL expression, exact for integer types."""

    name: str
    expression: str
    integer: bool = True

    @property
    def type(self) -> str:
        return "long" if self.integer else "double"


def tie_order(spec: DimensionSpec, row_key: tuple[str, ...], tie: str = "keyed") -> list[Column]:
    """What orders rows that agree on all keys of a dimension.

    ``keyed``: a digest of the dimension's name and the row's key, so that ties of two
    dimensions are independent of each other and make no false pattern. ``fast``: the same
    by two 64-bit hashes. ``columns``: the row's key itself, the same in all dimensions. Digests
    of 128 bits order all rows: the key need not be carried along.
    """
    key = [F.expr(k) for k in row_key]
    if tie == "keyed":
        return [keyed_digest(F.lit(spec.name), *[k.cast("string") for k in key])]
    if tie == "fast":
        return [F.xxhash64(F.lit(spec.name), *key), F.xxhash64(*key, F.lit(spec.name))]
    return key


def keyed_digest(name: Column, *key: Column) -> Column:
    """The 16 bytes that order ties of the dimension of this name; the key's columns as strings, or already joined by colons."""
    return F.unhex(F.md5(F.concat_ws(":", name, *key)))


def tie_sql(spec: DimensionSpec, row_key: tuple[str, ...]) -> str:
    key = ", ".join(f"CAST({k} AS VARCHAR)" for k in row_key)
    return f"md5(concat_ws(':', '{spec.name}', {key})), {', '.join(row_key)}"


def resolve(df: DataFrame, specs: list[DimensionSpec]) -> None:
    """Let the analyser check every key; unknown columns raise its error. Names must differ."""
    if len({s.name for s in specs}) < len(specs):
        raise ValueError("dimension names repeat")
    df.select(*[s.label() for s in specs], *[F.expr(k.removesuffix(" desc")) for s in specs for k in s.keys])  # analysed, not run
