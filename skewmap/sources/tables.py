"""Readers: the given tables, pairs from text formats, sequences from FASTA-like lines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators import kmertally, stats


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table's chosen columns; only they are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_pairs(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """Key-value rows from CSV, JSON, ORC, Parquet or text, with an explicit schema."""
    if fmt not in ("csv", "json", "orc", "parquet", "text"):
        raise ValueError(f"unknown format {fmt!r}")
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def read_sequences(spark: SparkSession, path: str) -> DataFrame:
    """(file, record, sequence) of FASTA-like text files: each ``>`` header begins a record.

    Files are cut at headers by the reader, so a large file is many rows and splits over many tasks, and a
    record's lines never leave their row. ``record`` rises within a file; text before the first header is no record.
    """
    place = F.struct(F.col("_metadata.file_block_start").alias("block"), F.monotonically_increasing_id().alias("i"))
    rows = spark.read.option("lineSep", "\n>").text(path).select("value", F.col("_metadata.file_path").alias("file"), place.alias("place"))
    first = F.broadcast(rows.groupBy("file").agg(F.min("place").alias("place"), F.lit(True).alias("first")))  # one row a file
    known = rows.join(first, ["file", "place"], "left").where(F.col("first").isNull() | F.startswith("value", F.lit(">")))
    body = F.regexp_replace(F.regexp_replace("value", "^[^\n]*\n?", ""), "[\r\n]+", "")
    return known.select("file", F.col("place.i").alias("record"), body.alias("sequence"))


def read_with_files(spark: SparkSession, path: str, merge: bool = True) -> DataFrame:
    """Parquet files under ``path``, partition columns found from folders and schemas merged, with each row's file."""
    return spark.read.option("mergeSchema", str(merge).lower()).parquet(path).select("*", F.col("_metadata.file_path").alias("file"))


# ---------------------------------------------------------------- k-mers


def _cut(texts: Column, size: int, k: int) -> Column:
    """An array of texts as one of pieces of at most ``size`` k-mers each; a place in a text is found by passing over what is before it."""
    return F.flatten(F.transform(texts, lambda t: F.transform(F.sequence(F.lit(1), F.length(t) - (k - 1), F.lit(size)), lambda i: F.substr(t, i, F.lit(size + k - 1)))))


def kmers(df: DataFrame, text: str, k: int, canonical: bool = False) -> DataFrame:
    """One row per k-character substring; ``canonical`` folds a nucleotide k-mer with its reverse complement."""
    pieces = df.where(F.length(text) >= k).select(F.explode(_cut(_cut(F.array(text), 4096, k), 64, k)).alias("piece"))
    grams = F.transform(F.sequence(F.lit(1), F.length("piece") - (k - 1)), lambda i: F.substr(F.col("piece"), i, F.lit(k)))
    out = pieces.select(F.explode(grams).alias("kmer"))
    return out.select(_canonical(F.col("kmer")).alias("kmer")) if canonical else out


def _canonical(kmer: Column) -> Column:
    return F.least(kmer, F.reverse(F.translate(kmer, "acgt", "tgca")))


def kmer_counts(df: DataFrame, text: str, k: int, canonical: bool = False) -> DataFrame:
    """(kmer, n): how often each k-mer occurs."""
    out = kmertally.tally(df, text, k)
    return out.groupBy(_canonical(F.col("kmer")).alias("kmer")).agg(F.sum("n").alias("n")) if canonical else out


def folded(df: DataFrame, text: str) -> DataFrame:
    """Texts as strings over a, c, g, t: lower-cased letters a-z, each by its place in the alphabet modulo 4."""
    letters = "abcdefghijklmnopqrstuvwxyz"
    kept = F.regexp_replace(F.lower(text), "[^a-z]", "")
    return df.select(F.translate(kept, letters, "".join("acgt"[i % 4] for i in range(26))).alias("seq"))


# ---------------------------------------------------------------- synthetic relations

ZIPF_SUPPORT, ZIPF_EXPONENT, UNIFORM_VALUES = 1000, 1.5, 100


def zipf_table(spark: SparkSession, support: int = ZIPF_SUPPORT, exponent: float = ZIPF_EXPONENT) -> DataFrame:
    """(value, lo, hi): cumulative shares of a Zipf distribution, a table of fixed size."""
    weight = [r**-exponent for r in range(1, support + 1)]
    total, acc, rows = sum(weight), 0.0, []
    for r, w in enumerate(weight, 1):
        rows.append((r, acc, acc + w / total if r < support else 1.1))
        acc += w / total
    return spark.createDataFrame(rows, "value long, lo double, hi double")


def synthetic_ranks(keys: DataFrame, key: str) -> DataFrame:
    """(key, r, u): each key's place from 1 in a portable mixed order, and its draw from [0, 1) for Zipf values."""
    mixed = (F.col(key) * F.lit(2654435761)) % F.lit(4294967296)
    placed = stats.ranked(keys.select(F.col(key).alias("key"), mixed.alias("m")), [F.col("m"), F.col("key")], "synthetic", "r")
    return placed.select("key", (F.col("r") + 1).alias("r"), (((F.col("key") * F.lit(40503) + F.lit(12345)) % F.lit(1000003)) / F.lit(1000003.0)).alias("u"))


def dominant_cut(total: Column, alpha: Column) -> Column:
    """As many keys as round() of the exact product of the total and a share of whole hundredths."""
    return F.floor(total * F.round(alpha * 100) / F.lit(100) + F.lit(0.5))


def synthetic(keys: DataFrame, key: str, alpha: float, dist: str) -> DataFrame:
    """(key, value): the first round(alpha N) keys in a portable mixed order get value 0, the others by ``dist``.

    ``unique``: a value of their own; ``uniform100``: one of 100; ``zipf``: Zipf 1.5 by a range join with the
    cumulative table. Ranks are prefix sums over a range-partitioned order, as the share has to be exact.
    """
    total = keys.agg(F.count(F.lit(1)).alias("total"))
    rows = synthetic_ranks(keys, key).crossJoin(F.broadcast(total))
    minority = F.col("r") > dominant_cut(F.col("total"), F.lit(alpha))
    if dist == "unique":
        return rows.select("key", F.when(minority, F.col("key") + 1).otherwise(0).cast("long").alias("value"))
    if dist == "uniform100":
        return rows.select("key", F.when(minority, F.col("r") % UNIFORM_VALUES + 1).otherwise(0).cast("long").alias("value"))
    if dist != "zipf":
        raise ValueError(f"unknown distribution {dist!r}")
    table_ = F.broadcast(zipf_table(keys.sparkSession))
    return rows.join(table_, (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi"))).select("key", F.when(minority, F.col("value")).otherwise(0).cast("long").alias("value"))


# ---------------------------------------------------------------- workloads on the given tables

WORKLOADS = ("lang", "toxic", "quality", "returnflag", "lines_per_order", "orders_per_cust", "part_supp", "order_part", "cust_date", "user_hour", "custkey", "extprice", "role", "doc_quality", "vec_label", "url_lang", "url_host", "words")
#: Values that are computed from the key: a key may stand in several rows, which then have the same value.
DERIVED = ("url_lang", "url_host")
#: A lineitem row's identity: these four columns together are unique.
ROW = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def workload(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, tuple[str, ...], str]:
    """A key -> value relation of the given tables: DataFrame, key columns, value column."""
    t = lambda n, *c: table(spark, sf_dir, n, *c)
    count = lambda df, *k: (df.groupBy(*k).agg(F.count(F.lit(1)).alias("n")), k, "n")
    if name == "lang":
        return t("documents", "doc_id", "lang"), ("doc_id",), "lang"
    if name in ("toxic", "quality"):
        return t("labels", "doc_id", name), ("doc_id",), name
    if name == "returnflag":
        return t("lineitem", *ROW, "l_returnflag"), ROW, "l_returnflag"
    if name == "extprice":
        return t("lineitem", *ROW, "l_extendedprice"), ROW, "l_extendedprice"
    if name == "lines_per_order":
        return count(t("lineitem", "l_orderkey"), "l_orderkey")
    if name == "orders_per_cust":
        return count(t("orders", "o_custkey"), "o_custkey")
    if name == "part_supp":
        return count(t("lineitem", "l_partkey", "l_suppkey"), "l_partkey", "l_suppkey")
    if name == "order_part":
        return count(t("lineitem", "l_orderkey", "l_partkey"), "l_orderkey", "l_partkey")
    if name == "cust_date":
        return count(t("orders", "o_custkey", "o_orderdate"), "o_custkey", "o_orderdate")
    if name == "user_hour":
        return count(t("events", "user_id", "ts").select("user_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")), "user_id", "hour")
    if name == "custkey":
        return t("orders", "o_orderkey", "o_custkey"), ("o_orderkey",), "o_custkey"
    if name == "role":
        return t("conversations", "conv_id", "turn", "role"), ("conv_id", "turn"), "role"
    if name == "doc_quality":
        return t("documents", "doc_id").join(t("labels", "doc_id", "quality"), "doc_id", "left"), ("doc_id",), "quality"
    if name == "vec_label":
        return t("embeddings", "vec_id", "label"), ("vec_id",), "label"
    if name == "url_lang":
        return t("pages", "url").select("url", F.split_part("url", F.lit("/"), F.lit(4)).alias("path")), ("url",), "path"
    if name == "url_host":
        return t("pages", "url").select("url", F.split_part("url", F.lit("/"), F.lit(3)).alias("host")), ("url",), "host"
    if name == "words":
        words = t("documents", "text").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("(\\S+)"), F.lit(1))).alias("word"))
        return count(words, "word")
    if name.startswith(("kmer", "fold")):
        return kmer_counts(*_kmer_texts(spark, sf_dir, name)), ("kmer",), "n"
    if name == "bench_flag":
        texts = t("documents", "text").withColumn("there", F.lit(False)).unionByName(t("benchmark", "text").withColumn("there", F.lit(True)))
        seen = kmertally.tally(texts, "text", 15, "there").where("n > n_side")
        return seen.select("kmer", (F.col("n_side") > 0).alias("hit")), ("kmer",), "hit"
    raise ValueError(f"unknown workload {name!r}")


def _kmer_texts(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, str, int]:
    """Texts of a k-mer workload, their column, and k."""
    if name.startswith("kmer"):
        return table(spark, sf_dir, "documents", "text"), "text", int(name[4:])
    return folded(table(spark, sf_dir, "conversations", "text"), "text"), "seq", int(name[4:])


def kmer_histogram(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(value, freq): how many k-mers of a k-mer workload occur ``value`` times."""
    return kmertally.histogram(*_kmer_texts(spark, sf_dir, name))
