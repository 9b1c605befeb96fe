"""Helpers shared by the text operators: Arrow views, word splitting, hashing."""

from __future__ import annotations

import ctypes
import gc
import re
from collections.abc import Callable, Iterator
from functools import reduce
from operator import and_

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cleaned, discard, partitions, release, shared, shared_dir, stored

materialise = stored
__all__ = ["cleaned", "discard", "materialise", "partitions", "release", "shared", "shared_dir"]

#: White space of every contract: blank and the bytes 9 to 13.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def residue(key: str, modulus: int) -> Column:
    """crc32 of the key written as text, modulo ``modulus``; a null key gives null."""
    return F.crc32(F.col(key).cast("string")) % F.lit(modulus)


def utf8_view(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a string column end to end, and row offsets into them; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    if column.null_count:
        column = column.fill_null(b"")
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offs[0] : offs[-1]], offs - offs[0]


def byte_rows(column: pa.Array) -> Iterator[bytes]:
    """Each row as bytes; null is empty."""
    raw, offs = utf8_view(column)
    blob = raw.tobytes()
    ends = offs.tolist()
    return (blob[a:b] for a, b in zip(ends[:-1], ends[1:]))


def in_parts(column: pa.Array, most: int = 6_000_000) -> Iterator[tuple[int, pa.Array]]:
    """Texts of a column in groups of about ``most`` bytes, with the first one's row."""
    size = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    group = np.cumsum(size) // most
    starts = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])) if len(size) else []
    for lo, hi in zip(starts, [*starts[1:], len(size)]):
        yield int(lo), column.slice(lo, hi - lo)


def words_of(text: bytes) -> list[bytes]:
    """Words of a text after lower-casing A-Z (bytes.lower and bytes.split know exactly these letters and spaces)."""
    return text.lower().split()


#: Rows of a stored side that every task may get in a join; rows of such sides have some dozens of bytes.
FEW = 500_000


def small(side: DataFrame) -> DataFrame:
    """``side`` to be broadcast if it was counted to have few rows; a side that grows beyond that is joined by an exchange."""
    return F.broadcast(side) if side.count() <= FEW else side


def without(docs: DataFrame, alike: dict[str, Column], fewer: DataFrame) -> DataFrame:
    """``docs`` less the rows that ``fewer`` takes away.

    ``alike`` are columns by which rows are told apart, under names that ``docs`` lacks. ``fewer`` is a stored
    table of them and ``stay``: how many (0 or 1) of the rows alike stay. Rows that are not in it all stay.
    """
    there = fewer.select(*(F.col(c).alias(f"__of{c}") for c in alike), F.col("stay").alias("__stay"))
    same = reduce(and_, (F.col(c).eqNullSafe(F.col(f"__of{c}")) for c in alike))
    joined = docs.withColumns(alike).join(small(there), same, "left")
    kept = joined.where(F.col("__stay").isNull())
    if fewer.where("stay = 1").limit(1).count():  # the same row several times
        kept = kept.unionByName(joined.where("__stay = 1").dropDuplicates(list(alike)))
    return kept.select(*docs.columns)


_caches: dict[str, Callable[[], None]] = {}


def remember(owner: str, forget: Callable[[], None]) -> None:
    """Tell how an operator's tables in this worker are emptied."""
    _caches[owner] = forget


_last: list[str] = []


def give_back() -> None:
    """Return memory that this process no longer uses to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # where the C library has it
    if trim is not None:
        trim(0)


def only(owner: str) -> None:
    """Empty the tables that other operators left in this worker: workers live on from one operator to the next.

    What they took is given back to the system, as a worker keeps it otherwise, beside an executor's heap.
    """
    if _last == [owner]:
        return
    for name, forget in _caches.items():
        if name != owner:
            forget()
    if _last:
        give_back()
    _last[:] = [owner]


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalising mixer over uint64 (multiply and xor-shift rounds)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_ASCII_LETTER = re.compile(rb"[A-Za-z]")


def has_letter(text: bytes) -> bool:
    """Whether a character of Unicode's letter categories is in the text; digits, number forms and marks are none."""
    return _ASCII_LETTER.search(text) is not None or any(map(str.isalpha, text.decode("utf-8", "replace")))
