"""Static key -> value relations: which columns are the key, and what the value is."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


class DuplicateKeys(ValueError):
    """Keys occur more than once and the policy is to refuse that."""


@dataclass(frozen=True)
class KeyValueSpec:
    """Key columns and value column of a relation.

    ``on_duplicate``: ``error``, ``first`` (smallest value), ``sum`` or ``max``.
    """

    keys: tuple[str, ...]
    value: str
    on_duplicate: str = "error"

    def check(self, df: DataFrame) -> None:
        for name in self.keys:
            kind = df.schema[name].dataType
            if isinstance(kind, (T.MapType, T.CalendarIntervalType, T.DayTimeIntervalType, T.YearMonthIntervalType)):
                raise TypeError(f"key column {name} has type {kind.simpleString()}, which cannot be hashed as a key")

    def rows(self, df: DataFrame) -> DataFrame:
        """Key columns and the value; one row per key, but for the policy ``error``, under which repeats are yet to be refused."""
        self.check(df)
        rows = df.select(*self.keys, self.value)
        how = {"first": F.min, "sum": F.sum, "max": F.max}.get(self.on_duplicate)
        if how is not None:
            return rows.groupBy(*self.keys).agg(how(self.value).cast(rows.schema[self.value].dataType).alias(self.value))
        if self.on_duplicate != "error":
            raise ValueError(f"unknown policy {self.on_duplicate!r}")
        return rows

    def refuse_repeats(self, rows: DataFrame, hashed: str | None = None) -> None:
        """Raise if a key occurs more than once. With a column of key hashes only rows that share one are compared by key."""
        if hashed is not None:
            again = rows.groupBy(hashed).agg(F.count(F.lit(1)).alias("__n")).where("__n > 1").drop("__n")
            if not again.limit(1).count():
                return
            rows = rows.join(again, hashed, "left_semi")
        twice = rows.groupBy(*self.keys).agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).collect()
        if twice:
            raise DuplicateKeys(f"key {twice[0].asDict()} occurs {twice[0]['n']} times")

    def pairs(self, df: DataFrame) -> DataFrame:
        """Key columns and the value, one row per key."""
        rows = self.rows(df)
        if self.on_duplicate == "error":
            self.refuse_repeats(rows)
        return rows


def canonical(df: DataFrame, name: str) -> Column:
    """A key column as it is hashed: doubles without signed zero and with one NaN, nested values as JSON."""
    kind = df.schema[name].dataType
    col = F.col(name)
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        wide = col.cast("double")
        return F.when(F.isnan(wide), F.lit(float("nan"))).when(wide == 0, F.lit(0.0)).otherwise(wide)
    if isinstance(kind, (T.StructType, T.ArrayType)):
        return F.to_json(F.struct(col.alias("v")))
    return col


def key_hash(df: DataFrame, keys: tuple[str, ...], seed: int = 0) -> Column:
    """64-bit hash of a composite key. A mask of nulls goes in first, as ``xxhash64`` passes over nulls."""
    mask = F.lit(0)
    for i, name in enumerate(keys):
        mask = mask.bitwiseOR(F.when(F.col(name).isNull(), F.lit(1 << (i % 30))).otherwise(F.lit(0)))
    return F.xxhash64(F.lit(seed), mask, *(canonical(df, k) for k in keys))
