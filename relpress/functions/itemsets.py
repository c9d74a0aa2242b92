"""Column expressions over itemsets, in Python and as SQL functions.

An itemset is an array of (p, v) structs ordered by position p: "column p has value v". A tuple of a relation is the
itemset of all its columns, so one form serves tuples, itemsets and the residual rows of entries.
"""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

ITEMS = "array<struct<p: int, v: int>>"


def as_items(columns: list[str], mask: Column | None = None) -> Column:
    """Itemset of the given columns, in their order, where the bit of ``mask`` is set (all where it is None)."""
    every = F.array(*[F.struct(F.lit(i).alias("p"), F.col(c).cast("int").alias("v")) for i, c in enumerate(columns)])
    return every if mask is None else masked(every, mask)


def masked(items: Column, mask: Column) -> Column:
    return F.filter(items, lambda x: F.getbit(mask, x["p"]) == 1)


def value_at(items: Column, position: int) -> Column:
    """The value an itemset gives to a position; null if it gives none."""
    return F.get(F.transform(F.filter(items, lambda x: x["p"] == position), lambda x: x["v"]), F.lit(0))


def mask_of(items: Column) -> Column:
    return F.aggregate(items, F.lit(0).cast("bigint"), lambda a, x: a + F.expr("1L").cast("bigint") * F.pow(F.lit(2), x["p"]).cast("bigint"))


def spread(items: Column, columns: list[str]) -> list[Column]:
    """One nullable column for each position."""
    return [value_at(items, i).alias(c) for i, c in enumerate(columns)]


def covers(itemset: Column, of: Column) -> Column:
    """Whether every item of ``itemset`` is in the tuple ``of``."""
    return F.forall(itemset, lambda x: F.array_contains(of, x))


def without_each(items: Column) -> Column:
    """All itemsets one item smaller."""
    return F.transform(items, lambda x: F.filter(items, lambda y: y["p"] != x["p"]))


def area(length: Column, frequency: Column) -> Column:
    return (length * frequency).cast("bigint")


def saving(length: Column, frequency: Column) -> Column:
    """Cells an entry saves: its values are stored once instead of once a tuple."""
    return (length * (frequency - 1)).cast("bigint")


def local_rate(length: Column, frequency: Column, arity: int) -> Column:
    """Saved share of the cells of the tuples that the itemset covers."""
    return saving(length, frequency) / (F.lit(arity) * frequency)


def score(objective: str, length: Column, frequency: Column, arity: int) -> Column:
    """What the choice of itemsets maximises, as an exactly comparable number."""
    if objective == "area":
        return area(length, frequency).cast("double")
    if objective == "savings":
        return saving(length, frequency).cast("double")
    if objective == "rate":
        return F.round(local_rate(length, frequency, arity), 12)
    if objective == "length":
        return length.cast("double")
    if objective == "freq":
        return frequency.cast("double")
    raise ValueError(f"no objective {objective!r}")


def register(spark: SparkSession) -> None:
    """The same as temporary SQL functions."""
    for name, args, kind, body in (
        ("itemset_covers", f"u {ITEMS}, t {ITEMS}", "BOOLEAN", "forall(u, x -> array_contains(t, x))"),
        ("mask_length", "mask BIGINT", "INT", "bit_count(mask)"),
        ("itemset_area", "len INT, freq BIGINT", "BIGINT", "len * freq"),
        ("entry_saving", "len INT, freq BIGINT", "BIGINT", "len * (freq - 1)"),
        ("entry_rate", "len INT, freq BIGINT, arity INT", "DOUBLE", "len * (freq - 1) / (arity * freq)"),
        ("itemset_parents", f"u {ITEMS}", f"array<{ITEMS}>", "transform(u, x -> filter(u, y -> y.p <> x.p))"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
