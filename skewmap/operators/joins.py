"""Joins around indexes: values as of a time, events near others, versions of an index."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof(events: DataFrame, changes: DataFrame, by: str, at: str, value: str, alias: str = "as_of") -> DataFrame:
    """``events`` with the value of the last change of the same key at or before the event; null before the first.

    Both sides go to one exchange by key as a union; a running last value does the join without pairs.
    """
    cols = events.columns
    left = events.select(*cols, F.lit(None).cast(changes.schema[value].dataType).alias("__v"), F.lit(1).alias("__side"))
    right = changes.select(*(F.col(c) if c in (by, at) else F.lit(None).cast(events.schema[c].dataType).alias(c) for c in cols), F.struct(F.col(value).alias("v")).alias("__w"), F.lit(0).alias("__side"))
    left = left.drop("__v").withColumn("__w", F.lit(None).cast(right.schema["__w"].dataType))
    order = Window.partitionBy(by).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = left.select(*cols, "__w", "__side").unionByName(right.select(*cols, "__w", "__side"))
    return both.withColumn("__l", F.last("__w", ignorenulls=True).over(order)).where("__side = 1").select(*cols, F.col("__l.v").alias(alias))


def interval(left: DataFrame, right: DataFrame, left_at: str, right_at: str, seconds: int, on: Column | None = None) -> DataFrame:
    """Pairs with ``right_at`` within ``seconds`` of ``left_at``: an equi-join on time bins, each left row in three bins at most."""
    sec = lambda c: F.unix_micros(F.col(c).cast("timestamp")) / 1e6
    bins = left.withColumn("__b", F.floor(sec(left_at) / seconds)).withColumn("__b", F.explode(F.array(F.col("__b") - 1, F.col("__b"), F.col("__b") + 1)))
    other = right.withColumn("__c", F.floor(sec(right_at) / seconds))
    cond = (F.col("__b") == F.col("__c")) & (F.abs(sec(left_at) - sec(right_at)) <= seconds)
    return bins.join(other, cond if on is None else cond & on).drop("__b", "__c")


def version_diff(old: DataFrame, new: DataFrame, keys: tuple[str, ...], value: str) -> DataFrame:
    """Keys that two versions of a relation answer differently: key, old, new, change (added, removed, changed)."""
    a = old.select(*(F.col(k).alias(f"__o_{k}") for k in keys), F.col(value).alias("old"), F.lit(True).alias("__a"))
    b = new.select(*keys, F.col(value).alias("new"), F.lit(True).alias("__b"))
    cond = F.lit(True)
    for k in keys:
        cond = cond & F.col(k).eqNullSafe(F.col(f"__o_{k}"))
    both = a.join(b, cond, "full_outer")
    kind = F.when(F.col("__a").isNull(), "added").when(F.col("__b").isNull(), "removed").when(~F.col("old").eqNullSafe(F.col("new")), "changed")
    return both.select(*(F.coalesce(k, f"__o_{k}").alias(k) for k in keys), "old", "new", kind.alias("change")).where("change is not null")


def salted(left: DataFrame, right: DataFrame, on: tuple[str, ...], salts: int) -> DataFrame:
    """Equi-join whose keys are each spread over ``salts`` tasks: rows of the left by their own hash, rows of the right in every one.

    A hot key's left rows meet in no one task; the price is ``salts`` times the right side.
    """
    own = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    every = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return own.join(every, [*on, "__salt"]).drop("__salt")
