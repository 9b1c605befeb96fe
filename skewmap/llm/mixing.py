"""Mixing sources to target weights by weighted fair queueing.

Every source is a queue of its documents in shuffled (key-hash) order, each standing ``repeats`` times. A
document is served in slices, a slice having at most a hundred-thousandth of its source's target or one word. A slice's virtual finish
time is the words its source has served up to and including it, divided by the source's target. All
slices of all sources are range-sorted by virtual finish time, and the order is truncated where its running
total reaches the total budget; a document takes what lies before. So each source comes within a few
slices of its target, whatever the length of its documents. Slices that begin so late that the order must end before
them are left out of the sort. ``mixed_documents`` takes documents whole, as texts are never shortened: those of which
at least half lies before the cut.

Both running totals, a source's and the order's, are prefix sums over range partitions: each partition adds up
its own rows and only one total per (queue, partition) is summed across partitions, so a source with a
third of the rows is spread over many tasks.

Defined results: null text has size 0, takes nothing and stays in the output; a null source is a source
of its own and last in order; sources of size 0 get target 0; an empty table gives no rows; ties in the
hash are broken by key, size and the row's other columns; a null key has a place like any other; rows that repeat a
key are separate documents; rows equal in all columns are, too; extra columns are ignored by ``mix`` and kept by
``mixed_documents``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from . import common

#: Weights of the sources by code point order, repeating.
WEIGHTS = (5.0, 2.0, 1.0)
#: Slices of a source's target.
SLICES = 100_000


def n_words(text: Column) -> Column:
    """Number of words, counted without building them: the text is reduced to word starts."""
    squeezed = F.trim(F.regexp_replace(F.coalesce(text, F.lit("")), common.SPACE, " "))
    return F.when(squeezed == "", 0).otherwise(F.length(squeezed) - F.length(F.replace(squeezed, F.lit(" "), F.lit(""))) + 1).cast("long")


def shares(sizes: list[tuple[str | None, int]], budget: float = 1.5, repeats: float = 2.0, weights: tuple[float, ...] = WEIGHTS) -> list[tuple[str | None, int, float]]:
    """(source, size, target) by code point, null last. Targets stop at ``repeats`` times the size; what is left over is shared again by weight."""
    order = sorted(sizes, key=lambda x: (x[0] is None, (x[0] or "").encode("utf-32-be")))
    weight = [weights[i % len(weights)] for i in range(len(order))]
    size = [n for _, n in order]
    total, target, open_ = budget * sum(size), [0.0] * len(order), {i for i, n in enumerate(size) if n}
    while open_:
        left = total - sum(target[i] for i in range(len(order)) if i not in open_)
        unit = left / sum(weight[i] for i in open_)
        over = {i for i in open_ if weight[i] * unit > repeats * size[i]}
        for i in open_:
            target[i] = float(repeats * size[i]) if i in over else weight[i] * unit
        if not over:
            break
        open_ -= over
    return [(name, n, t) for (name, n), t in zip(order, target)]


def running_total(rows: DataFrame, queue: str | None, order: list[str], value: str, total: str) -> DataFrame:
    """Adds ``total``: the sum of ``value`` up to and including each row in its queue, as a prefix sum over range partitions.

    Without ``queue`` all rows are one queue. The stored table that the sums are taken from fixes the ranges.
    """
    queues = [queue] if queue else []
    placed = rows.repartitionByRange(common.partitions(rows.sparkSession), *queues, *order).withColumn("__part", F.spark_partition_id())
    placed = common.materialise(placed, "queue")
    within = Window.partitionBy("__part", *queues).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    before = Window.partitionBy(*queues).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)  # over one row a partition
    sums = placed.groupBy("__part", *queues).agg(F.sum(value).alias("__sum")).withColumn("__before", F.coalesce(F.sum("__sum").over(before), F.lit(0)))
    offsets = sums.select(F.col("__part").alias("__p"), *(F.col(q).alias("__q") for q in queues), "__before")
    same = F.col("__part") == F.col("__p")
    for q in queues:
        same = same & F.col(q).eqNullSafe(F.col("__q"))
    joined = placed.withColumn("__own", F.sum(value).over(within)).join(offsets, same)
    return joined.withColumn(total, F.col("__own") + F.col("__before")).drop("__part", "__own", "__before", "__p", "__q")


def _hashable(kind: T.DataType) -> bool:
    if isinstance(kind, T.ArrayType):
        return _hashable(kind.elementType)
    if isinstance(kind, T.StructType):
        return all(_hashable(f.dataType) for f in kind.fields)
    return not isinstance(kind, (T.MapType, T.VariantType))


def mark(docs: DataFrame) -> Column:
    """Hash of all columns of a row (maps and variants aside)."""
    return F.xxhash64(*(F.col(f"`{f.name}`") for f in docs.schema.fields if _hashable(f.dataType)))


def _last(targets: list[tuple[str | None, int, float]], slices: int, repeats: int) -> float:
    """Virtual time by which the order has reached the budget.

    A source that has not served all its words lags by less than a slice, and at time 1 + x every such source has
    passed its target by x of it; sources that have served all give their targets in full.
    """
    running = [t for _, n, t in targets if 0 < t < repeats * n]
    return 1 + 1e-9 + (sum(1 + t / slices for t in running) + 1) / sum(running) if running else 1 + 1e-9


@common.cleaned
def mix(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", budget: float = 1.5, repeats: int = 2, weights: tuple[float, ...] = WEIGHTS, slices: int = SLICES) -> DataFrame:
    """One row per document: key, size, source_size, target, taken, first_finish (virtual time of its first copy, null if not taken), copies (whole ones of which at least half is taken), mark."""
    spark = docs.sparkSession
    rows = docs.select(F.col(key).alias("k"), F.col(source).cast("string").alias("s"), n_words(F.col(text)).alias("n"), F.xxhash64(F.col(key).cast("string"), F.lit(77)).alias("h"), mark(docs).alias("m"), F.monotonically_increasing_id().alias("row"))
    rows = common.materialise(rows, "sizes")
    # One row per source: as many as there are sources, which is not the number of documents.
    targets = shares([(r["s"], r["n"] or 0) for r in rows.groupBy("s").agg(F.sum("n").alias("n")).collect()], budget, repeats, weights)
    words, end = round(sum(t for _, _, t in targets)), _last(targets, slices, repeats)
    table = spark.createDataFrame(targets, "__s string, source_size long, target double")
    queued = running_total(rows, "s", ["h", "k", "n", "m", "row"], "n", "served")
    wide = common.materialise(queued.join(F.broadcast(table), F.col("s").eqNullSafe(F.col("__s"))).select("k", "m", "row", "n", "source_size", "target", "served"), "served")
    # A document stands once for every time it may be served, from the words served before; slices of it likewise.
    slots = wide.where("n > 0 and target > 0").select("row", "n", "target", F.greatest(F.lit(1), F.floor(F.col("target") / slices)).alias("slice"), F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(repeats - 1)), lambda r: F.col("served") - F.col("n") + F.col("source_size") * r)).alias("time", "begin"))
    cut = slots.where(F.col("begin") <= F.col("target") * end).select("row", "time", "target", "n", "begin", "slice", F.explode(F.sequence(F.lit(0).cast("long"), F.expr("(n - 1) div slice"))).alias("i"))
    size = F.least("slice", F.col("n") - F.col("i") * F.col("slice"))
    order = cut.select("row", "time", "i", size.alias("size"), ((F.col("begin") + F.col("i") * F.col("slice") + size) / F.col("target")).alias("finish"))
    order = running_total(order, None, ["finish", "row", "time", "i"], "size", "total")
    part = F.greatest(F.lit(0), F.least("size", F.lit(words) - F.col("total") + F.col("size")))
    taken = order.groupBy("row").agg(*(F.sum(F.when(F.col("time") == r, part).otherwise(0)).alias(f"t{r}") for r in range(repeats)))
    all_ = wide.join(taken, "row", "left").fillna(0, [f"t{r}" for r in range(repeats)])
    total, copies = F.lit(0).cast("long"), F.lit(0)
    for r in range(repeats):
        total = total + F.col(f"t{r}")
        copies = copies + ((F.col(f"t{r}") * 2 >= F.col("n")) & (F.col("n") > 0)).cast("int")
    return all_.select(F.col("k").alias(key), F.col("n").alias("size"), "source_size", "target", total.alias("taken"), F.when(total > 0, F.col("served") / F.col("target")).alias("first_finish"), copies.alias("copies"), F.col("m").alias("mark"))


def mixed_documents(docs: DataFrame, key: str = "doc_id", **options) -> DataFrame:
    """The mix itself: ``docs`` with all its columns in order of virtual time, a document taken twice standing twice.

    All sources run at their weights, so words are even over virtual time: a partition holds an equal span of it.
    """
    plan = mix(docs, key, **options)
    alike = {"__key": F.col(key), "__mark": mark(docs)}
    # Rows equal in all columns have their slots in common: one row of them takes all.
    again = plan.groupBy(F.col(key).alias("__key"), F.col("mark").alias("__mark")).count().where("count > 1").select("__key", "__mark", F.lit(1).alias("stay"))
    times = F.transform(F.sequence(F.lit(0), F.col("copies") - 1), lambda r: F.col("first_finish") + r * F.col("source_size") / F.col("target"))
    slots = plan.where("copies > 0").select(F.col(key).alias("__k"), F.col("mark").alias("__m"), F.explode(times).alias("__at"))
    single = common.without(docs, alike, again).withColumns(alike)
    out = single.join(slots, F.col("__key").eqNullSafe(F.col("__k")) & (F.col("__mark") == F.col("__m")))
    n = common.partitions(docs.sparkSession)
    out = out.withColumn("__span", F.least(F.lit(n - 1), F.floor(F.col("__at") * n).cast("int"))).repartitionById(n, "__span")
    return out.sortWithinPartitions("__at", "__key", "__mark").select(*docs.columns)


def op9_mixing(spark, sf_dir: str) -> DataFrame:
    return mix(common.documents(spark, sf_dir)).drop("copies", "mark")
