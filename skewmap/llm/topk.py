"""Exact top-k search by inner product: tiled matrix products and tree merging of per-query lists.

Queries are cut into tiles and vectors into lanes; each (lane, tile) cell gets its rows in key order, forms
matrix products of the tile with one block of vectors after the other, selects each query's best of block and
running list, and hands on one list per query. The lists of a query's lanes are merged in two levels. A
cell holds one tile and one block, so memory is bounded whatever the table's size. Work is queries times
vectors, as the search is exact.

Components become integers, floor(scale * x), which travel in the narrowest type that holds them all. Products are formed in float64 while every possible score is
below 2**50, and in 64-bit integers beyond.

Defined results: vectors that are null or hold null or non-finite components are neither queries nor
candidates; only vectors of a query's own length are compared with it; ties go to the smaller key; all
rows with the query's key are its own; repeated candidates are listed as often as they stand; a query
with no candidate has no rows; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common

#: Queries of a tile, vectors of a block, most vectors of a lane, and least vectors that are worth a lane of their own.
TILE, BLOCK, LANE_ROWS, LANE_LEAST = 4096, 4096, 1 << 20, 8192
#: Score of what is no candidate; its negative is a number, too.
LOWEST = np.iinfo(np.int64).min + 1


def integers(vector: Column, scale: int) -> Column:
    return F.transform(vector, lambda x: F.floor(x.cast("double") * scale).cast("long"))


def usable(vector: Column) -> Column:
    wide = lambda x: x.cast("double")
    return vector.isNotNull() & F.coalesce(F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(wide(x)) & (F.abs(wide(x)) < float("inf"))), F.lit(False))


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row the k best scores and their ids, best first; among equals the column that stands first."""
    n = scores.shape[1]
    k = min(k, n)
    if n and np.abs(scores[scores != LOWEST]).max(initial=0) < (1 << 62) // max(n, 1):
        key = np.where(scores == LOWEST, LOWEST + n, scores * n) + (n - 1 - np.arange(n))
        part = np.argpartition(-key, k - 1, axis=1)[:, :k] if k < n else np.broadcast_to(np.arange(n), scores.shape)
        part = np.take_along_axis(part, np.argsort(-np.take_along_axis(key, part, 1), axis=1), 1)
    else:
        part = np.argsort(-scores, axis=1, kind="stable")[:, :k]
    ids = np.broadcast_to(ids, scores.shape)
    return np.take_along_axis(scores, part, 1), np.take_along_axis(ids, part, 1)


def _cell(query_ids: np.ndarray, queries: np.ndarray, blocks: Iterator[tuple[np.ndarray, np.ndarray]], k: int) -> tuple[np.ndarray, np.ndarray]:
    """Top lists of a tile over blocks of candidates that come in key order."""
    top = np.full((len(query_ids), 0), LOWEST, np.int64)
    ids = np.zeros((len(query_ids), 0), np.int64)
    for own, block in blocks:
        most = float(np.abs(queries).max(initial=0)) * float(np.abs(block).max(initial=0)) * max(1, block.shape[1])
        scores = np.rint(queries.astype(np.float64) @ block.T.astype(np.float64)).astype(np.int64) if most < 2.0**50 else queries @ block.T
        scores[query_ids[:, None] == own[None, :]] = LOWEST
        s, i = _best(scores, own[None, :], k)
        both, named = np.concatenate([top, s], 1), np.concatenate([ids, i], 1)
        part = np.argsort(-both, axis=1, kind="stable")[:, :k]  # earlier blocks have smaller keys
        top, ids = np.take_along_axis(both, part, 1), np.take_along_axis(named, part, 1)
    return top, ids


def _search(k: int):
    """For ``mapInArrow`` over rows (cell, dim, kind, id, vector) sorted by cell, kind and id: lists (query_id, ids, scores)."""

    def lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, qi, qv, ci, cv, top = None, [], [], [], [], None

        def matrix(parts: list) -> np.ndarray:
            return np.concatenate(parts).astype(np.int64) if parts else np.zeros((0, 0), np.int64)

        def block() -> None:
            nonlocal top, ci, cv
            if not ci or not qi:
                ci, cv = [], []
                return
            own, vec = np.concatenate(ci), matrix(cv)
            s, i = _cell(np.concatenate(qi), matrix(qv), iter([(own, vec)]), k)
            if top is not None:
                s, i = np.concatenate([top[0], s], 1), np.concatenate([top[1], i], 1)
                part = np.argsort(-s, axis=1, kind="stable")[:, :k]
                s, i = np.take_along_axis(s, part, 1), np.take_along_axis(i, part, 1)
            top, ci, cv = (s, i), [], []

        def done() -> pa.RecordBatch | None:
            block()
            if top is None:
                return None
            real = top[0] != LOWEST
            edges = pa.array(np.concatenate([[0], np.cumsum(real.sum(1))]).astype(np.int32))
            make = lambda x: pa.ListArray.from_arrays(edges, pa.array(x[real]))
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(qi)), make(top[1]), make(top[0])], ["query_id", "ids", "scores"])

        for batch in batches:
            at = batch.column(0).to_numpy(zero_copy_only=False)
            kind = batch.column(1).to_numpy(zero_copy_only=False)
            ids = batch.column(2).to_numpy(zero_copy_only=False)
            vec = batch.column(3)
            flat, edges = vec.values.to_numpy(zero_copy_only=False), vec.offsets.to_numpy()
            cuts = np.flatnonzero((at[1:] != at[:-1]) | (kind[1:] != kind[:-1])) + 1
            for a, b in zip([0, *cuts], [*cuts, len(at)]):
                if a == b:
                    continue
                if at[a] != cell:
                    if cell is not None and (out := done()) is not None:
                        yield out
                    cell, qi, qv, ci, cv, top = at[a], [], [], [], [], None
                part = flat[edges[a] : edges[b]].reshape(b - a, -1)
                if kind[a] == 0:
                    qi.append(ids[a:b])
                    qv.append(part)
                elif qi:
                    for lo in range(0, b - a, BLOCK):
                        ci.append(ids[a:b][lo : lo + BLOCK])
                        cv.append(part[lo : lo + BLOCK])
                        if sum(map(len, ci)) >= BLOCK:
                            block()
        if cell is not None and (out := done()) is not None:
            yield out

    return lists


@common.cleaned
def top_k(vectors: DataFrame, is_query: Column, k: int = 20, key: str = "vec_id", vector: str = "embedding", scale: int = 64) -> DataFrame:
    """The k best candidates of every query: query_id, rank, key, score."""
    spark = vectors.sparkSession
    rows = vectors.where(usable(F.col(vector)) & F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), integers(F.col(vector), scale).alias("v"), is_query.alias("q"))
    rows = common.materialise(rows.withColumn("d", F.size("v")).withColumn("h", F.xxhash64("id", "v")), "vectors")
    least, most = F.min(F.array_min("v")), F.max(F.array_max("v"))
    shape = rows.groupBy("d").agg(F.count(F.lit(1)).alias("n"), F.count_if("q").alias("q"), least.alias("least"), most.alias("most")).agg(F.max("n").alias("n"), F.max("q").alias("q"), F.min("least").alias("least"), F.max("most").alias("most")).first()
    n, q = shape["n"] or 0, shape["q"] or 0
    tiles, lanes = max(1, -(-q // TILE)), max(1, -(-n // LANE_ROWS))
    # Lanes for all tasks, if there are vectors for them: what is merged later grows with the lanes.
    lanes = max(lanes, min(-(-common.partitions(spark) // tiles), n // LANE_LEAST))
    top = max(abs(shape["least"] or 0), abs(shape["most"] or 0) + 1)
    narrow = "smallint" if top <= 1 << 15 else "int" if top <= 1 << 31 else "bigint"
    rows = rows.withColumn("v", F.col("v").cast(f"array<{narrow}>"))
    spread = lambda m: F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    asked = rows.where("q").select(spread(lanes).alias("lane"), F.pmod("h", F.lit(tiles)).cast("int").alias("tile"), "d", F.lit(0).alias("kind"), "id", "v")
    given = rows.select(F.pmod(F.shiftright("h", 20), F.lit(lanes)).cast("int").alias("lane"), spread(tiles).alias("tile"), "d", F.lit(1).alias("kind"), "id", "v")
    both = asked.unionByName(given).withColumn("cell", (F.col("d").cast("long") * tiles + F.col("tile")) * lanes + F.col("lane"))
    cells = both.repartition(max(common.partitions(spark), min(tiles * lanes, 20_000)), "cell").sortWithinPartitions("cell", "kind", "id").select("cell", "kind", "id", "v")
    found = cells.mapInArrow(_search(k), "query_id long, ids array<long>, scores array<long>")
    # Tree merge: lists of a query meet in groups of lanes, then once more.
    ranked = found.select("query_id", F.posexplode(F.arrays_zip("ids", "scores")).alias("p", "x")).select("query_id", F.col("x.ids").alias("id"), F.col("x.scores").alias("score"))
    if lanes > 64:
        first = Window.partitionBy("query_id", F.pmod(F.xxhash64("id"), F.lit(int(lanes**0.5)))).orderBy(F.desc("score"), "id")
        ranked = ranked.withColumn("r", F.row_number().over(first)).where(F.col("r") <= k).drop("r")
    last = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return ranked.withColumn("rank", F.row_number().over(last)).where(F.col("rank") <= k).select("query_id", "rank", F.col("id").alias(key), "score")


def op4_exact_top_k(spark, sf_dir: str) -> DataFrame:
    return top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 20 == 0)


#: The same search in SQL. It forms every product in SQL and is for small tables.
ORACLE_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 64) AS BIGINT)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(CAST(q.e AS DOUBLE[]), CAST(c.e AS DOUBLE[])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0
), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""
