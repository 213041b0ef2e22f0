"""Filter masks from cell numbers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from packvec.operators import predicates as pr
from packvec.operators.attributes import Attribute


def condition(c: pr.Condition, a: Attribute, mode: str = "exact") -> Column:
    """A row's cell looked up in the pass table. Straddling cells: exact compares the number, inclusive passes, strict fails."""
    table = F.array(*map(F.lit, pr.cell_pass(c, a))) if a.cells else F.array().cast("array<int>")
    code = F.get(table, F.col(f"c_{a.name}").cast("int"))
    x, i = F.col(f"x_{a.name}"), pr.interval(c, a)
    raw = F.lit(True)
    if i.lo != float("-inf"):
        raw = raw & ((x > i.lo) if i.lo_open else (x >= i.lo))
    if i.hi != float("inf"):
        raw = raw & ((x < i.hi) if i.hi_open else (x <= i.hi))
    straddle = {"exact": raw, "inclusive": F.lit(True), "strict": F.lit(False)}[mode]
    # A null attribute fails every condition.
    return F.coalesce(F.when(code == pr.STRADDLE, straddle).otherwise(code == pr.PASS), F.lit(False))


def mask(predicate: pr.Predicate, attributes: dict[str, Attribute], mode: str = "exact") -> Column:
    """AND over the conditions of a clause, OR over clauses; all attributes left out pass."""
    out = F.lit(not predicate)
    for clause in predicate:
        held = F.lit(True)
        for c in clause:
            held = held & condition(c, attributes[c.attribute], mode)
        out = out | held
    return out


def code_range(predicate: pr.Predicate, attributes: dict[str, Attribute]) -> Column:
    """A condition on cell numbers alone that every passing row meets: it reaches the files' statistics as a pushed filter."""
    if len(predicate) != 1:
        return F.lit(True)
    out = F.lit(True)
    for c in predicate[0]:
        cells = [i for i, v in enumerate(pr.cell_pass(c, attributes[c.attribute])) if v != pr.FAIL]
        code = F.col(f"c_{c.attribute}")
        out = out & (code.between(min(cells), max(cells)) if cells else F.lit(False))
    return out


def steps(df: DataFrame, predicate: pr.Predicate, attributes: dict[str, Attribute]) -> DataFrame:
    """Rows left after each condition of a one-clause predicate: step, attribute, n_pass."""
    (clause,) = predicate
    held, columns = F.lit(True), []
    for i, c in enumerate(clause):
        held = held & condition(c, attributes[c.attribute])
        columns.append(F.struct(F.lit(i).alias("step"), F.lit(c.attribute).alias("attribute"), F.count_if(held).alias("n_pass")))
    return df.agg(F.array(*columns).alias("s")).select(F.inline("s"))


def per_partition(df: DataFrame, passing: Column, *by: str) -> DataFrame:
    """by, part_id, n_pass."""
    return df.groupBy(*by, "part_id").agg(F.count_if(passing).alias("n_pass"))


def bitmap(df: DataFrame, passing: Column) -> DataFrame:
    """part_id, bucket, bitmap of the local positions that pass (local_pos counts from 0, bitmaps from 1)."""
    at = F.col("local_pos") + 1
    return df.where(passing).groupBy("part_id", F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bitmap"))
