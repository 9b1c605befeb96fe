"""Registered queries of the relational surroundings: joins, aggregates, windows, set operations and sketches around
key-value relations, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.bounds import lower_bound
from .operators import joins
from .session import shared_dir, ship
from .sources import tables

Query = Callable[[SparkSession, str], DataFrame]


def _t(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return tables.table(ship(spark), sf_dir, name, *columns)


def _bit_aggregates(spark, sf_dir):
    """Words of a small bit map and its population, by language: what a union of Bloom cells is made of."""
    mixed = (F.col("doc_id") * 2654435761) % 4294967296
    d = _t(spark, sf_dir, "documents", "doc_id", "lang").withColumn("m", mixed)
    return d.groupBy("lang").agg(F.bit_or("m").alias("any_bits"), F.bit_and("m").alias("all_bits"), F.bit_xor("m").alias("odd_bits"), F.bitmap_count(F.bitmap_construct_agg(F.col("m") % 32768)).alias("cells_set"))


_BIT_SQL = """WITH d AS (SELECT lang, (doc_id * 2654435761) % 4294967296 AS m FROM documents)
SELECT lang, bit_or(m) AS any_bits, bit_and(m) AS all_bits, bit_xor(m) AS odd_bits, count(DISTINCT m % 32768) AS cells_set FROM d GROUP BY lang"""


def _bitmap_union(spark, sf_dir):
    """A bit map a shard, then their union: the cells of one map over all keys."""
    d = _t(spark, sf_dir, "documents", "doc_id").withColumn("cell", (F.col("doc_id") * 40503) % 32768)
    shards = d.groupBy((F.col("doc_id") % 7).alias("shard")).agg(F.bitmap_construct_agg("cell").alias("bits"))
    return shards.agg(F.bitmap_count(F.bitmap_or_agg("bits")).alias("cells_set"), F.count(F.lit(1)).alias("shards"))


_BITMAP_SQL = "SELECT count(DISTINCT (doc_id * 40503) % 32768) AS cells_set, count(DISTINCT doc_id % 7) AS shards FROM documents"


def _statistics(spark, sf_dir):
    rows = _t(spark, sf_dir, "lineitem", "l_returnflag", "l_quantity", "l_extendedprice").select("l_returnflag", F.col("l_quantity").cast("double").alias("x"), F.col("l_extendedprice").cast("double").alias("y"))
    return rows.groupBy("l_returnflag").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.avg("y"), 4).alias("mean"), F.round(F.stddev_samp("y"), 3).alias("deviation"), F.round(F.corr("x", "y"), 6).alias("correlation"),
        F.round(F.covar_samp("x", "y"), 2).alias("covariance"), F.round(F.regr_slope("y", "x"), 4).alias("slope"),
    )


_STATISTICS_SQL = """WITH r AS (SELECT l_returnflag, CAST(l_quantity AS DOUBLE) AS x, CAST(l_extendedprice AS DOUBLE) AS y FROM lineitem)
SELECT l_returnflag, count(*) AS n, round(avg(y), 4) AS mean, round(stddev_samp(y), 3) AS deviation, round(corr(x, y), 6) AS correlation, round(covar_samp(x, y), 2) AS covariance, round(regr_slope(y, x), 4) AS slope FROM r GROUP BY 1"""


def _share_ranks(spark, sf_dir):
    """Each supplier's customers of a kind in tenths, with their relative ranks: windows by nation, so no window has all rows."""
    s = _t(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal")
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return s.select("c_custkey", F.ntile(10).over(w).alias("tenth"), F.round(F.percent_rank().over(w), 6).alias("below"), F.round(F.cume_dist().over(w), 6).alias("upto"))


_SHARE_SQL = """SELECT c_custkey, CAST(ntile(10) OVER w AS INTEGER) AS tenth, round(percent_rank() OVER w, 6) AS below, round(cume_dist() OVER w, 6) AS upto
FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)"""


def _moving_share(spark, sf_dir):
    """For every event its user's events of the hour before, and the share of its own kind among them."""
    e = _t(spark, sf_dir, "events", "event_id", "user_id", "event_type", "ts").withColumn("s", F.unix_seconds(F.col("ts").cast("timestamp")))
    hour = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    own = Window.partitionBy("user_id", "event_type").orderBy("s").rangeBetween(-3600, 0)
    out = e.withColumn("n", F.count(F.lit(1)).over(hour)).withColumn("k", F.count(F.lit(1)).over(own))
    return out.select("event_id", "n", F.round(F.col("k") / F.col("n"), 6).alias("share"))


_MOVING_SQL = """WITH e AS (SELECT event_id, user_id, event_type, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events)
SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n,
round(count(*) OVER (PARTITION BY user_id, event_type ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) / count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 6) AS share FROM e"""


def _order_steps(spark, sf_dir):
    """A customer's orders in time with the days since the last one, and the first and last price so far."""
    o = _t(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_totalprice")
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    days = F.datediff(F.col("o_orderdate"), F.lag("o_orderdate").over(w))
    return o.select("o_orderkey", days.alias("days"), F.lead("o_orderkey").over(w).alias("next_order"), F.first_value("o_orderkey").over(w).alias("first_order"), F.nth_value("o_orderkey", 2).over(w).alias("second_order"))


_STEPS_SQL = """SELECT o_orderkey, CAST(date_diff('day', CAST(lag(o_orderdate) OVER w AS DATE), CAST(o_orderdate AS DATE)) AS INTEGER) AS days, lead(o_orderkey) OVER w AS next_order, first_value(o_orderkey) OVER w AS first_order, nth_value(o_orderkey, 2) OVER w AS second_order
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"""


def _star(spark, sf_dir):
    """Line items through orders, customers, nations and regions: counts of a composite key."""
    line, orders = _t(spark, sf_dir, "lineitem", "l_orderkey", "l_returnflag"), _t(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    customer, nation, region = _t(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), _t(spark, sf_dir, "nation", "n_nationkey", "n_name", "n_regionkey"), _t(spark, sf_dir, "region", "r_regionkey", "r_name")
    wide = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    wide = wide.join(nation, F.col("c_nationkey") == F.col("n_nationkey")).join(region, F.col("n_regionkey") == F.col("r_regionkey"))
    return wide.groupBy("r_name", "n_name", "l_returnflag").agg(F.count(F.lit(1)).alias("n"))


_STAR_SQL = """SELECT r_name, n_name, l_returnflag, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2, 3"""


def _lateral(spark, sf_dir):
    """Every nation's two richest customers, by a lateral subquery."""
    _t(spark, sf_dir, "nation", "n_nationkey", "n_name").createOrReplaceTempView("__nation")
    _t(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal").createOrReplaceTempView("__customer")
    return spark.sql("SELECT n_name, c_custkey FROM __nation, LATERAL (SELECT c_custkey FROM __customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)")


_LATERAL_SQL = "SELECT n_name, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)"


def _salted(spark, sf_dir):
    """Pairs of line items of one supplier's part, counted by supplier: a self join whose hot keys are salted."""
    rows = _t(spark, sf_dir, "lineitem", *tables.ROW)
    a = rows.select("l_partkey", "l_suppkey", F.struct("l_orderkey", "l_linenumber").alias("one"))
    b = a.withColumnRenamed("one", "other")
    pairs = joins.salted(a, b, ("l_partkey", "l_suppkey"), 4).where(F.col("one") < F.col("other"))
    return pairs.groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("pairs"))


_SALTED_SQL = """SELECT a.l_suppkey, count(*) AS pairs FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey AND a.l_suppkey = b.l_suppkey
AND (a.l_orderkey < b.l_orderkey OR (a.l_orderkey = b.l_orderkey AND a.l_linenumber < b.l_linenumber)) GROUP BY 1"""


def _partitioned(spark, sf_dir):
    """Documents written by source and read again: the folder gives the column, and only the folders asked for are read."""
    import uuid

    path = f"{shared_dir(spark).rstrip('/')}/skewmap-by-source-{uuid.uuid4().hex}"
    _t(spark, sf_dir, "documents", "doc_id", "lang", "source").where("source is not null").write.partitionBy("source").parquet(path)
    back = tables.read_with_files(spark, path)
    return back.groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("lang").alias("langs"), (F.count_distinct("file") > 0).alias("has_files"))


_PARTITIONED_SQL = "SELECT source, count(*) AS n, count(DISTINCT lang) AS langs, true AS has_files FROM documents WHERE source IS NOT NULL GROUP BY 1"


def _grouping_sets(spark, sf_dir):
    _t(spark, sf_dir, "documents", "lang", "source").createOrReplaceTempView("__documents")
    return spark.sql("SELECT lang, source, count(*) AS n, CAST(grouping_id(lang, source) AS BIGINT) AS level FROM __documents GROUP BY GROUPING SETS ((lang, source), (lang), (source), ())")


_GROUPING_SQL = "SELECT lang, source, count(*) AS n, CAST(grouping_id(lang, source) AS BIGINT) AS level FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), (source), ())"


def _set_operations(spark, sf_dir):
    """Keys of two versions of a relation: in both, in one, in either, with and without repeats."""
    d = _t(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_quantity")
    a, b = d.where("l_quantity <= 30").select("l_partkey", "l_suppkey"), d.where("l_quantity > 20").select("l_partkey", "l_suppkey")
    kinds = {"both": a.intersect(b), "both_all": a.intersectAll(b), "first_only": a.subtract(b), "first_only_all": a.exceptAll(b), "either": a.union(b).distinct(), "either_all": a.unionByName(b)}
    out = None
    for name, rows in kinds.items():
        one = rows.agg(F.lit(name).alias("kind"), F.count(F.lit(1)).alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


_A, _B = "SELECT l_partkey, l_suppkey FROM lineitem WHERE l_quantity <= 30", "SELECT l_partkey, l_suppkey FROM lineitem WHERE l_quantity > 20"
_SET_SQL = " UNION ALL ".join(
    f"SELECT '{name}' AS kind, count(*) AS n FROM (({_A}) {op} ({_B}))" for name, op in (("both", "INTERSECT"), ("both_all", "INTERSECT ALL"), ("first_only", "EXCEPT"), ("first_only_all", "EXCEPT ALL"), ("either", "UNION"), ("either_all", "UNION ALL"))
)


def _sketches(spark, sf_dir):
    """Sketches of a shard each, merged, beside the exact answers."""
    d = _t(spark, sf_dir, "lineitem", "l_orderkey", "l_returnflag", "l_quantity").withColumn("shard", F.col("l_orderkey") % 5)
    shards = d.groupBy("shard").agg(F.hll_sketch_agg("l_orderkey", F.lit(14)).alias("hll"), F.count(F.lit(1)).alias("n"))
    merged = shards.agg(F.hll_sketch_estimate(F.hll_union_agg("hll")).alias("estimate"), F.sum("n").alias("n"))
    # Beside a distinct count, the other aggregates would keep a sketch of each order.
    several = d.agg(F.countDistinct("l_orderkey").alias("exact"))
    exact = d.agg(F.percentile_approx("l_quantity", 0.5, 10_000).alias("median"), F.expr("percentile(l_quantity, 0.5)").alias("middle"), F.expr("approx_top_k(l_returnflag, 1)[0].item").alias("top"))
    top = d.groupBy("l_returnflag").count().orderBy(F.desc("count"), "l_returnflag").limit(1).select(F.col("l_returnflag").alias("most"))
    return merged.crossJoin(several).crossJoin(exact).crossJoin(top).select("n", (F.abs(F.col("estimate") / F.col("exact") - 1) < 0.05).alias("distinct_near"), (F.abs(F.col("median") - F.col("middle")) <= 1).alias("median_near"), (F.col("top") == F.col("most")).alias("top_found"))


_SKETCH_SQL = "SELECT count(*) AS n, true AS distinct_near, true AS median_near, true AS top_found FROM lineitem"


def _array_sums(spark, sf_dir):
    """An order's line quantities as one array, summed and counted inside the row."""
    d = _t(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_quantity")
    rows = d.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_linenumber", F.col("l_quantity").cast("double").alias("q")))).alias("x"))
    return rows.select("l_orderkey", F.aggregate("x", F.lit(0.0), lambda a, v: a + v["q"]).alias("total"), F.size("x").cast("long").alias("lines"), F.array_max(F.transform("x", lambda v: v["q"])).alias("most"))


_ARRAY_SQL = "SELECT l_orderkey, sum(CAST(l_quantity AS DOUBLE)) AS total, count(*) AS lines, max(CAST(l_quantity AS DOUBLE)) AS most FROM lineitem GROUP BY 1"


def _panels(spark, sf_dir, grid: Callable[[SparkSession], DataFrame], ratio: float):
    """Two best settings of every share and family, and how far each is from the best of its share."""
    g = grid(ship(spark)).withColumn("bound", lower_bound(F.col("alpha"), F.col("eps"), F.col("bits"), F.lit(ratio)))
    panel = Window.partitionBy("alpha", "family").orderBy(F.desc("bound"), "param")
    out = g.withColumn("regret", F.max("bound").over(Window.partitionBy("alpha")) - F.col("bound")).withColumn("place", F.row_number().over(panel)).where("place <= 2")
    return out.select("alpha", "family", "place", "param", F.round("regret", 6).alias("regret"))


QUERIES: dict[str, tuple[Query, str]] = {
    "bit_aggregates": (_bit_aggregates, _BIT_SQL), "bitmap_union": (_bitmap_union, _BITMAP_SQL), "price_statistics": (_statistics, _STATISTICS_SQL), "share_ranks": (_share_ranks, _SHARE_SQL),
    "moving_share": (_moving_share, _MOVING_SQL), "order_steps": (_order_steps, _STEPS_SQL), "star_join": (_star, _STAR_SQL), "lateral_top": (_lateral, _LATERAL_SQL), "salted_self_join": (_salted, _SALTED_SQL),
    "partitioned_read": (_partitioned, _PARTITIONED_SQL), "alpha_grouping_sets": (_grouping_sets, _GROUPING_SQL), "key_set_operations": (_set_operations, _SET_SQL), "merged_sketches": (_sketches, _SKETCH_SQL), "array_sums": (_array_sums, _ARRAY_SQL),
}
