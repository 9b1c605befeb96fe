"""Profiles of key -> value relations: all that planners and codes need to know, from one aggregation."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import partitions, stored


@dataclass(frozen=True)
class Profile:
    """Number of keys, of distinct values, of keys with the dominant value, and that value (least of a tie)."""

    num_keys: int
    distinct_values: int
    dominant_count: int
    dominant: object = None

    @property
    def alpha(self) -> float:
        return self.dominant_count / self.num_keys if self.num_keys else 1.0

    @property
    def ratio(self) -> float:
        return self.distinct_values / self.num_keys if self.num_keys else 0.0


def ranked(df: DataFrame, order: list[Column], name: str = "ranked", rank: str = "rank") -> DataFrame:
    """``df`` with each row's place, from 0, in a total order, without gathering the rows in one task.

    Rows are range-partitioned in the order, ranked within their partitions, and moved up by the sizes of the
    partitions before, one row a partition. The stored table fixes the ranges.
    """
    placed = df.repartitionByRange(partitions(df.sparkSession), *order).withColumn("__part", F.spark_partition_id())
    placed = stored(placed, name)
    within = F.row_number().over(Window.partitionBy("__part").orderBy(*order)) - 1
    before = F.coalesce(F.sum("n").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = placed.groupBy("__part").agg(F.count(F.lit(1)).alias("n")).select("__part", before.alias("__start"))
    out = placed.withColumn("__within", within).join(F.broadcast(starts), "__part")
    return out.select(*df.columns, (F.col("__start") + F.col("__within")).cast("long").alias(rank))


def value_histogram(df: DataFrame, value: str) -> DataFrame:
    """(value, freq): partial counts are formed before the exchange, so a hot value costs one row a task."""
    return df.groupBy(F.col(value).alias("value")).agg(F.count(F.lit(1)).alias("freq"))


def freq_of_freq(histogram: DataFrame) -> DataFrame:
    """(freq, multiplicity): at most about sqrt(2 N) rows, whatever the number of values."""
    return histogram.groupBy("freq").agg(F.count(F.lit(1)).alias("multiplicity"))


def profile_frame(df: DataFrame, value: str) -> DataFrame:
    """One row: num_keys, distinct_values, dominant_count, dominant. A null value is a symbol and last in ties."""
    return profile_of(value_histogram(df, value))


def profile_of(hist: DataFrame) -> DataFrame:
    """``profile_frame`` from a histogram, which is read twice."""
    rank = F.struct(F.col("freq").alias("f"), F.col("value").isNotNull().alias("known"))
    top = F.max(rank)
    totals = hist.agg(F.coalesce(F.sum("freq"), F.lit(0)).alias("num_keys"), F.count(F.lit(1)).alias("distinct_values"), F.coalesce(top["f"], F.lit(0)).alias("dominant_count"))
    first = hist.orderBy(F.desc("freq"), F.asc_nulls_last("value")).limit(1).select(F.col("value").alias("dominant"))
    return totals.join(first, how="left")


def profile(df: DataFrame, value: str) -> Profile:
    row = profile_frame(df, value).first()
    return Profile(row["num_keys"], row["distinct_values"], row["dominant_count"], row["dominant"])


def sketch_profile(df: DataFrame, value: str, share: float = 0.01, confidence: float = 0.99, seed: int = 0) -> Profile:
    """Profile from a sample and a sketch: a lower limit of the dominant share, an upper limit of distinct values.

    Planning only needs these two, and a lower share and more values can only make a planner gate less, so the
    limits keep its decision safe with the given confidence (Hoeffding's inequality for the share; three
    standard errors of the distinct count).
    """
    row = df.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct(value, 0.02).alias("d"), F.max(F.col(value).isNull()).alias("null")).first()
    n = row["n"]
    if not n:
        return Profile(0, 0, 0)
    sample = df.sample(share, seed) if n * share >= 1000 else df
    top = value_histogram(sample, value).orderBy(F.desc("freq"), F.asc_nulls_last("value"))
    total = sample.count()
    first = top.first()
    slack = math.sqrt(math.log(1 / (1 - confidence)) / (2 * total)) if n * share >= 1000 else 0.0
    low = max(0.0, first["freq"] / total - slack)
    return Profile(n, min(n, math.ceil(row["d"] * 1.06) + bool(row["null"])), int(low * n), first["value"])


def entropy(histogram: DataFrame) -> DataFrame:
    """One row: entropy of the value distribution in bits per key."""
    total = histogram.agg(F.sum("freq").alias("total"))
    p = F.col("freq") / F.col("total")
    return histogram.crossJoin(F.broadcast(total)).agg(F.coalesce(F.sum(-p * F.log2(p)), F.lit(0.0)).alias("entropy"))
