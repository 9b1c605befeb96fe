"""Watching a value distribution that changes: windows of the dominant share, replanning, and deltas over an index."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.bounds import DELTA3
from ..operators.index import Index
from ..operators.stats import Profile
from ..plans.planner import Plan, gap_plan


def counts(events: DataFrame, value: str, window: Column, at: str = "ts", late: str | None = "10 minutes") -> DataFrame:
    """(start, end, value, freq) by time window; on a stream, rows later than the watermark are dropped."""
    rows = events.withWatermark(at, late) if late and events.isStreaming else events
    return rows.groupBy(window.alias("w"), F.col(value).alias("value")).agg(F.count(F.lit(1)).alias("freq")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "value", "freq")


def tumbling(events: DataFrame, value: str, size: str = "1 day", at: str = "ts") -> DataFrame:
    return counts(events, value, F.window(at, size), at)


def sliding(events: DataFrame, value: str, size: str = "1 day", step: str = "12 hours", at: str = "ts") -> DataFrame:
    return counts(events, value, F.window(at, size, step), at)


def session(events: DataFrame, value: str, gap: str = "30 minutes", at: str = "ts", late: str | None = "10 minutes", by: tuple[str, ...] = ()) -> DataFrame:
    """(by, start, end, num_keys, distinct_values, dominant_count, alpha) of sessions: rows less than ``gap`` apart, of all values together.

    A session window groups by time (and ``by``) alone, so its values are counted inside: pairs of a value and its
    number are merged over the session's rows. A session's state is bounded by its number of different values.
    """
    rows = events.withWatermark(at, late) if late and events.isStreaming else events
    kept = rows.select(*by, at, F.col(value).alias("value"))
    if events.isStreaming:
        # One aggregation, as sessions cannot be aggregated again before they are complete.
        sessions = kept.groupBy(F.session_window(at, gap).alias("w"), *by).agg(F.collect_list("value").alias("values"), F.count(F.lit(1)).alias("num_keys"))
        kinds = F.array_distinct("values")
        freqs = F.transform(kinds, lambda v: F.size(F.filter("values", lambda x: x.eqNullSafe(v))))
        out = sessions.select(*by, F.col("w.start").alias("start"), F.col("w.end").alias("end"), (F.col("num_keys")).alias("num_keys"), F.size(kinds).cast("long").alias("distinct_values"), F.array_max(freqs).cast("long").alias("dominant_count"))
        return out.withColumn("alpha", F.col("dominant_count") / F.col("num_keys"))
    # Batch: sessions begin where the row before is a gap or more away; values are then counted by session.
    order = Window.partitionBy(*by).orderBy(at)
    if not by:
        tagged = _global_sessions(kept, gap, at)
    else:
        step = F.unix_micros(F.col(at).cast("timestamp")) - F.lag(F.unix_micros(F.col(at).cast("timestamp"))).over(order)
        tagged = kept.withColumn("s", F.sum(F.when(step < _micros(gap), 0).otherwise(1)).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    grouped = tagged.groupBy(*by, "s", "value").agg(F.min(at).alias("a"), F.max(at).alias("z"), F.count(F.lit(1)).alias("freq"))
    out = grouped.groupBy(*by, "s").agg(F.min("a").alias("start"), F.max("z").alias("z"), F.sum("freq").alias("num_keys"), F.count(F.lit(1)).alias("distinct_values"), F.max("freq").alias("dominant_count"))
    return out.select(*by, "start", (F.col("z") + F.expr(f"INTERVAL {gap}")).alias("end"), "num_keys", "distinct_values", "dominant_count", (F.col("dominant_count") / F.col("num_keys")).alias("alpha"))


def _micros(gap: str) -> int:
    n, unit = gap.split()
    return int(n) * {"second": 1, "minute": 60, "hour": 3600, "day": 86400}[unit.rstrip("s")] * 1_000_000


def _global_sessions(rows: DataFrame, gap: str, at: str) -> DataFrame:
    """Rows with their session's number ``s`` where all rows are one sequence in time.

    Times are first reduced to one row a bin of the gap's length (first and last time in it), so what one window orders
    is bounded by the number of bins, not of rows; a bin can begin a session but hold no gap of its length.
    """
    micros, width = F.unix_micros(F.col(at).cast("timestamp")), _micros(gap)
    binned = rows.withColumn("b", F.floor(micros / width))
    bins = binned.groupBy("b").agg(F.min(micros).alias("first"), F.max(micros).alias("last"))
    order = Window.orderBy("b")
    begins = (F.col("first") - F.lag("last").over(order) >= width) | F.lag("last").over(order).isNull()
    numbered = bins.withColumn("new", begins.cast("int")).withColumn("s", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return binned.join(numbered.select("b", "s"), "b").drop("b")


def drift(windows: DataFrame) -> DataFrame:
    """(start, end, num_keys, distinct_values, dominant_count, alpha) of finished windows."""
    return windows.groupBy("start", "end").agg(F.sum("freq").alias("num_keys"), F.count(F.lit(1)).alias("distinct_values"), F.max("freq").alias("dominant_count")).withColumn("alpha", F.col("dominant_count") / F.col("num_keys"))


def needs_replan(current: Plan, profile: Profile, families=("fuse3",), delta: float = DELTA3) -> bool:
    """Whether the plan's decision or setting is no longer the planner's."""
    new = gap_plan(profile, families, delta)
    return (new.use_gate, new.family, new.param) != (current.use_gate, current.family, current.param)


def replan_sink(current: Callable[[], Plan], rebuild: Callable[[Profile, Plan], None], families=("fuse3",)) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch`` on (value, freq) counts: calls ``rebuild`` when the counts seen so far change the plan."""
    total: dict[str, DataFrame] = {}

    def run(batch: DataFrame, _: int) -> None:
        from ..session import stored

        seen = batch.select("value", "freq")
        if "all" in total:
            seen = total["all"].unionByName(seen)
        total["all"] = stored(seen.groupBy("value").agg(F.sum("freq").alias("freq")), "drift")
        row = total["all"].agg(F.sum("freq").alias("n"), F.count(F.lit(1)).alias("d"), F.max("freq").alias("top")).first()
        if not row["n"]:
            return
        profile = Profile(row["n"], row["d"], row["top"])
        if needs_replan(current(), profile, families):
            rebuild(profile, gap_plan(profile, families))

    return run


def running_share(events: DataFrame, group: str, value: str) -> DataFrame:
    """Running dominant share per group on a stream, by ``transformWithStateInPandas`` with a map of counts as state."""
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor

    class Shares(StatefulProcessor):
        def init(self, handle):
            self.counts = handle.getMapState("counts", "value string", "n long")

        def handleInputRows(self, key, rows, timers):
            for frame in rows:
                for v, n in frame[value].astype(str).value_counts().items():
                    old = self.counts.getValue((v,))[0] if self.counts.containsKey((v,)) else 0
                    self.counts.updateValue((v,), (int(old + n),))
            ns = [n for (n,) in self.counts.values()]
            yield pd.DataFrame({group: [key[0]], "num_keys": [sum(ns)], "alpha": [max(ns) / sum(ns)]})

        def close(self):
            pass

    kind = events.schema[group].dataType.simpleString()
    return events.groupBy(group).transformWithStateInPandas(Shares(), f"{group} {kind}, num_keys long, alpha double", "Update", "None")


#: Bytes up to which an index is sent to every executor for lookups of a stream.
STREAM_BYTES = 256 << 20


def stream_lookup(stream: DataFrame, index: Index) -> DataFrame:
    """Values for the keys of a stream: every batch is probed against a broadcast index.

    Shards, codebook and exceptions are each checked against ``STREAM_BYTES`` first; a larger index is refused, to be
    looked up in ``foreachBatch``. Keys whose hashes collide get their values from the exceptions, as in a lookup.
    """
    import numpy as np
    import pyarrow as pa

    from ..operators import gates, huffman
    from ..operators.index import ranks_in_shard
    from ..session import shared
    from ..sources.keyvalue import key_hash

    m = index.manifest
    size = (index.shards.agg(F.sum(F.octet_length("cells") + F.octet_length("gate"))).first()[0] or 0) + index.book_bytes + 200 * m.exceptions
    if size > STREAM_BYTES:
        raise ValueError(f"the index has {size} bytes; look up its keys in foreachBatch instead")
    shards = {r["shard"]: (bytes(r["gate"] or b""), bytes(r["cells"] or b"")) for r in index.shards.select("shard", "gate", "cells").collect()}
    handle = shared(index.shards.sparkSession, shards)
    code, family = huffman.Code(*m.code), gates.named(m.plan.family) if m.plan.use_gate else None

    def rank(h):
        h = h.to_numpy(zero_copy_only=False)
        out, own = np.zeros(len(h), np.int64), h % m.shards
        for s in np.unique(own):
            at = np.flatnonzero(own == s)
            out[at] = ranks_in_shard(m, family, code, *handle.value.get(int(s), (b"", b"")), h[at])
        return pa.array(out)

    rank.__annotations__ = {"h": pa.Array, "return": pa.Array}
    rank = F.arrow_udf(rank, "long")
    book = index.codebook.select(F.col("rank").alias("__rank"), F.col("value").alias(m.value))
    found = stream.withColumn("__rank", rank(key_hash(stream, m.keys, m.seed))).join(F.broadcast(book), "__rank", "left").drop("__rank")
    if not m.exceptions:
        return found
    odd = index.exceptions.select(*(F.col(k).alias(f"__e_{k}") for k in m.keys), F.col(m.value).alias("__e_value"), F.lit(True).alias("__e"))
    same = F.lit(True)
    for k in m.keys:
        same = same & F.col(k).eqNullSafe(F.col(f"__e_{k}"))
    value = F.when(F.col("__e"), F.col("__e_value")).otherwise(F.col(m.value)).alias(m.value)
    return found.join(F.broadcast(odd), same, "left").select(*stream.columns, value)


def deduplicated(events: DataFrame, keys: list[str], at: str = "ts", late: str = "10 minutes") -> DataFrame:
    """A stream's events, each key once within the watermark."""
    return events.withWatermark(at, late).dropDuplicatesWithinWatermark(keys) if events.isStreaming else events.dropDuplicates(keys)


def stream_interval(left: DataFrame, right: DataFrame, on: str, left_at: str, right_at: str, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: rows of ``right`` (its columns renamed by the caller) with the same key at most ``within`` after one of ``left``.

    Both watermarks and the time bound let Spark drop state that can match no more.
    """
    a = left.withWatermark(left_at, late) if left.isStreaming else left
    b = right.withWatermark(right_at, late) if right.isStreaming else right
    other = f"__{on}"
    b = b.withColumnRenamed(on, other)
    near = (F.col(right_at) >= F.col(left_at)) & (F.col(right_at) <= F.col(left_at) + F.expr(f"INTERVAL {within}"))
    return a.join(b, (F.col(on) == F.col(other)) & near).drop(other)


def overlay_lookup(index: Index, overlay: DataFrame, keys: DataFrame) -> DataFrame:
    """Values from a base index and a small overlay (keys, value, op, ts): the last change wins, deleted keys give null."""
    m = index.manifest
    last = overlay.groupBy(*m.keys).agg(F.max_by(F.struct(m.value, "op"), "ts").alias("__o"))
    last = last.select(*(F.col(k).alias(f"__o_{k}") for k in m.keys), "__o")
    cond = F.lit(True)
    for k in m.keys:
        cond = cond & F.col(k).eqNullSafe(F.col(f"__o_{k}"))
    base = index.lookup(keys)
    out = base.join(last, cond, "left")
    new = F.when(F.col("__o").isNull(), F.col(m.value)).when(F.col("__o.op") == "delete", F.lit(None)).otherwise(F.col(f"__o.{m.value}"))
    return out.withColumn(m.value, new).select(*base.columns)


def merged(base: DataFrame, overlay: DataFrame, keys: tuple[str, ...], value: str) -> DataFrame:
    """The relation that base and overlay stand for, to rebuild an index from."""
    last = overlay.groupBy(*keys).agg(F.max_by(F.struct(F.col(value).alias("v"), "op"), "ts").alias("__o"))
    kept = base.join(last.select(*keys), list(keys), "left_anti").select(*keys, value)
    return kept.unionByName(last.where("__o.op != 'delete'").select(*keys, F.col("__o.v").alias(value)))
