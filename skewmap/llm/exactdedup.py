"""Exact duplicate removal with a log-structured merge index, in DataFrame operations only.

Memtable: rows of some input partitions, aggregated by digest. Flush: a memtable becomes a run, one row
per digest in digest order in the shared folder, with a Bloom filter: blocks of bits, one row a block, which a
digest finds by its hash. Compaction: every run's digests are looked up in the other runs' filters; those that
none of them can hold are compact already, and the rest are merged, keeping the smallest identifier and the
sum of the counts. Rows are reduced before they leave their task, so a group of copies of any size
contributes a row per task. Hits, the digests of more than one row, receive byte verification: their normalised
texts are grouped by their bytes, again reduced in each task first. A digest whose texts differ (never
seen with SHA-256) is split by text.

Decisions come from the index. Rows find their group's entry by digest; a digest with over a thousandth of
all rows, of which there are less than a thousand, is sent to every task, so no task gets a large group.

Defined results: null text counts as empty; texts are equal after each run of white space becomes one
blank; a null identifier sorts after all others; rows that repeat an identifier are separate rows; of rows
that are equal in identifier and text one stays, no matter which; an empty table gives no rows; extra
columns, whatever their names, are left out of the decisions and kept by ``exact_dedup``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), common.SPACE, " ")


#: Runs that are flushed, bits of a block of a run's filter (Spark's bitmaps have as many), and filter bits a digest.
MEMTABLES, BLOCK_BITS, BITS = 4, 32_768, 16
#: A digest of over one in ``HOT`` rows is hot; less than ``HOT`` digests can be.
HOT = 1000


def _places(digest: Column, blocks: int) -> tuple[Column, list[Column]]:
    """Block of a digest in the filters, and its bits there."""
    h = F.xxhash64(digest, F.lit(9))
    return F.pmod(h, F.lit(blocks)), [F.pmod(F.xxhash64(digest, F.lit(10 + i)), F.lit(BLOCK_BITS)) for i in range(2)]


def _has(bits: Column, place: Column) -> Column:
    byte = F.conv(F.hex(F.substring(bits, (place / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("long")
    return F.coalesce(F.getbit(byte, (place % 8).cast("int")) == 1, F.lit(False))


class MergeIndex:
    """Log-structured index from digest to the smallest identifier that has it. ``digests`` tells about how many it will hold."""

    def __init__(self, digests: int = 1 << 20) -> None:
        self.runs: list[DataFrame] = []
        self.filters: list[DataFrame] = []
        self.blocks = max(1, -(-digests * BITS // BLOCK_BITS))

    def flush(self, entries: DataFrame) -> None:
        """Add a run of ``(digest, least, copies)`` rows: one row per digest, in digest order, and its filter."""
        run = entries.groupBy("digest").agg(F.min("least").alias("least"), F.sum("copies").alias("copies"))
        run = common.materialise(run.sortWithinPartitions("digest"), "run")
        block, places = _places(F.col("digest"), self.blocks)
        bits = run.select(block.alias("block"), F.explode(F.array(*places)).alias("place")).groupBy("block").agg(F.bitmap_construct_agg("place").alias("bits"))
        self.runs.append(run)
        self.filters.append(common.materialise(bits, "filter"))

    def lookup(self, digests: DataFrame) -> DataFrame:
        """``digests`` with ``maybe``: for each run whether its filter may hold the digest; never false for one it holds."""
        block, places = _places(F.col("digest"), self.blocks)
        all_ = None
        for i, f in enumerate(self.filters):
            f = f.select("block", F.lit(i).alias("run"), "bits")
            all_ = f if all_ is None else all_.unionByName(f)
        # One row a block: at most as many blocks as runs are gathered, of fixed size each.
        byrun = all_.groupBy("block").agg(F.map_from_entries(F.collect_list(F.struct("run", "bits"))).alias("__bits"))
        found = digests.withColumn("__block", block).join(byrun.withColumnRenamed("block", "__block"), "__block", "left")
        tests = [F.coalesce(_has(F.col("__bits")[i], places[0]) & _has(F.col("__bits")[i], places[1]), F.lit(False)) for i in range(len(self.filters))]
        return found.withColumn("maybe", F.array(*tests)).drop("__block", "__bits")

    def compact(self) -> DataFrame:
        """All runs as one (digest, least, copies)."""
        if len(self.runs) == 1:
            return self.runs[0]
        runs = None
        for i, run in enumerate(self.runs):
            run = run.withColumn("run", F.lit(i))
            runs = run if runs is None else runs.unionByName(run)
        looked = common.materialise(self.lookup(runs).withColumn("shared", F.size(F.filter("maybe", lambda x: x)) > 1).drop("maybe", "run"), "looked")
        merged = looked.where("shared").groupBy("digest").agg(F.min("least").alias("least"), F.sum("copies").alias("copies"))
        merged = merged.unionByName(looked.where("not shared").drop("shared"))
        self.runs, self.filters = [common.materialise(merged, "run")], []
        return self.runs[0]


@common.cleaned
def decide(docs: DataFrame, key: str = "doc_id", text: str = "text", memtables: int = MEMTABLES) -> DataFrame:
    """One row per row of ``docs``: key, keep_id, group_size, kept, text_sha256."""
    rows = docs.select(F.col(key).alias("id"), normalised(F.col(text)).alias("t"))
    digest = F.unhex(F.sha2("t", 256)).alias("digest")
    # Rows are numbered once, where they are stored, so that rows equal in identifier and text are told apart.
    digests = common.materialise(rows.select("id", digest, F.monotonically_increasing_id().alias("row"), F.pmod(F.spark_partition_id(), F.lit(memtables)).alias("memtable")), "digests")
    total = digests.count()
    index = MergeIndex(total)
    least = F.struct(F.col("id").isNull().alias("last"), "id", "row")
    for i in range(memtables):
        index.flush(digests.where(F.col("memtable") == i).select("digest", least.alias("least"), F.lit(1).cast("long").alias("copies")))
    hits = common.materialise(index.compact().where("copies > 1"), "hits")
    # Byte verification: rows that share a digest must share their bytes. Texts of other digests stay where they are.
    hot = F.broadcast(hits.where(F.col("copies") * HOT > total).select("digest"))
    few = common.small(hits.where(F.col("copies") * HOT <= total).select("digest"))
    texts = rows.select("t", digest)
    texts = texts.join(hot, "digest", "left_semi").unionByName(texts.join(hot, "digest", "left_anti").join(few, "digest", "left_semi")).groupBy("digest", "t").count()
    clash = common.materialise(texts.groupBy("digest").agg(F.count(F.lit(1)).alias("texts")).where("texts > 1").select("digest"), "clash")
    groups = hits.select("digest", F.col("least.id").alias("keep_id"), F.col("least.row").alias("first"), F.col("copies").alias("group_size"))
    odd = None
    if clash.limit(1).count():  # one digest, several texts: those rows are grouped by text
        group = Window.partitionBy("digest", "t")
        odd = rows.select("id", "t", digest).join(clash, "digest", "left_semi").withColumn("n", F.row_number().over(group.orderBy(F.asc_nulls_last("id"))))
        odd = odd.select("id", "digest", F.min("id").over(group).alias("keep_id"), F.count(F.lit(1)).over(group).alias("group_size"), (F.col("n") == 1).alias("kept"))
        digests = digests.join(clash, "digest", "left_anti")
    hot = F.broadcast(groups.where(F.col("group_size") * HOT > total))
    few = common.small(groups.where(F.col("group_size") * HOT <= total))
    known = digests.join(hot, "digest")
    others = digests.join(hot, "digest", "left_anti").join(few, "digest", "left")
    kept = F.coalesce(F.col("row") == F.col("first"), F.lit(True)).alias("kept")
    keep_id = F.when(F.col("first").isNull(), F.col("id")).otherwise(F.col("keep_id")).alias("keep_id")
    found = known.select("id", "digest", keep_id, "group_size", kept).unionByName(others.select("id", "digest", keep_id, "group_size", kept))
    found = found if odd is None else found.unionByName(odd)
    return found.select(F.col("id").alias(key), "keep_id", F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"), "kept", F.lower(F.hex("digest")).alias("text_sha256"))


@common.cleaned
def _fewer(docs: DataFrame, key: str, text: str) -> DataFrame:
    """(__key, __text, stay): how many rows of a key and text stay, where not all do."""
    found = decide(docs, key, text).where("group_size > 1")
    rows = found.groupBy(F.col(key).alias("__key"), F.unhex("text_sha256").alias("__text")).agg(F.count_if("kept").alias("stay"), F.count(F.lit(1)).alias("n"))
    return rows.where("stay < n").drop("n")


def exact_dedup(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with all its columns and one row of each group of equal texts: the one of smallest key."""
    alike = {"__key": F.col(key), "__text": F.unhex(F.sha2(normalised(F.col(text)), 256))}
    return common.without(docs, alike, _fewer(docs, key, text))


def op3_exact_dedup(spark, sf_dir: str) -> DataFrame:
    return decide(common.documents(spark, sf_dir))


ORACLE_SQL = r"""
WITH n AS (
  SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents
), g AS (SELECT t, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT n.doc_id, g.keep_id, g.group_size, n.doc_id = g.keep_id AS kept, sha256(n.t) AS text_sha256
FROM n JOIN g ON n.t = g.t
"""
