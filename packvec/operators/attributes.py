"""Attributes as numbers, their cells (M18) and dictionaries."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

NUMERIC = (T.NumericType, T.DateType, T.TimestampType, T.TimestampNTZType, T.BooleanType)


@dataclass
class Attribute:
    """A column's domain: edges of its cells on a number line. Categories lie at their ranks in sorted order.

    ranks: value -> rank for categories, else empty. A category's cell holds one value, so no predicate straddles it.
    """

    name: str
    kind: str  # "numeric" or "category"
    edges: list[float]
    values: list[str] = field(default_factory=list)

    @property
    def cells(self) -> int:
        return len(self.values) if self.kind == "category" else max(1, len(self.edges) - 1)


def number(df: DataFrame, name: str) -> Column:
    """The column as double: microseconds for timestamps, days for dates."""
    kind = df.schema[name].dataType
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(F.col(name).cast("timestamp")).cast("double")
    if isinstance(kind, T.DateType):
        return F.unix_date(name).cast("double")
    return F.col(name).cast("double")


def dictionary(df: DataFrame, name: str) -> DataFrame:
    """value, code of a category in sorted order from 0; null has no code."""
    found = df.where(F.col(name).isNotNull()).select(F.col(name).cast("string").alias("value")).distinct()
    from pyspark.sql import Window

    return found.withColumn("code", F.row_number().over(Window.orderBy("value")) - 1)


def describe(df: DataFrame, names: list[str], bits: int = 5, most_values: int = 10_000) -> dict[str, Attribute]:
    """Domains of columns: equal-depth cells for numbers (2 ** bits of them at most), dictionaries for the rest.

    A category may have most_values values; more are refused, as the dictionary is held by the driver and all tasks.
    """
    out = {}
    for name in names:
        if isinstance(df.schema[name].dataType, NUMERIC):
            x = number(df, name)
            share = [i / 2**bits for i in range(2**bits + 1)]
            row = df.agg(F.percentile_approx(x, share, 10_000).alias("e"), F.min(x).alias("lo"), F.max(x).alias("hi")).first()
            edges = sorted({row["lo"], row["hi"], *row["e"]}) if row["e"] else [0.0, 0.0]
            out[name] = Attribute(name, "numeric", edges if len(edges) > 1 else edges * 2)
        else:
            values = [r["value"] for r in dictionary(df, name).orderBy("code").limit(most_values + 1).collect()]
            if len(values) > most_values:
                raise ValueError(f"{name} has over {most_values} values")
            out[name] = Attribute(name, "category", [float(i) for i in range(len(values) + 1)], values)
    return out


def quantized(df: DataFrame, attributes: dict[str, Attribute], codes: str = "c_", numbers: str = "x_") -> DataFrame:
    """df with, for each attribute, its cell (null for null) and its number (a category's rank)."""
    out = df
    for a in attributes.values():
        if a.kind == "category":
            ranks = F.create_map(*[y for i, v in enumerate(a.values) for y in (F.lit(v), F.lit(i))]) if a.values else F.lit(None).cast("map<string,int>")
            code = ranks[F.col(a.name).cast("string")]
            x = code.cast("double")
        else:
            x = number(df, a.name)
            edges = F.array(*map(F.lit, a.edges))
            code = F.when(x.isNotNull(), F.greatest(F.least(F.size(F.filter(edges, lambda e: e <= x)) - 1, F.lit(a.cells - 1)), F.lit(0)))
        out = out.withColumns({f"{codes}{a.name}": code.cast("smallint"), f"{numbers}{a.name}": x})
    return out
