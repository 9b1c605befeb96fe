"""Removal of repeated runs of lines by fingerprints of whole passages, in DataFrame operations only.

A line's hash stands for it. A passage counts if it has ``window`` lines or one of ``long_words`` words, and
``min_words`` words in all. The winnowing windows are the least passages that count: from every line the shortest
that begins there, and to every line the shortest that ends there, at most two a line. A window's fingerprint is the
128-bit hash of all its lines, not of its least line alone, so windows that only share a common line do not
meet. A repeated run that counts is the union of the windows inside it, and those are chosen by their own lines
only, so every copy of the run has the same: fingerprints are guaranteed. Positions are joined with the first
occurrence (smallest key, then line) of their fingerprint, and matches extend both ways window by window, as the
windows that follow and go before are matched likewise; every occurrence but the first is a repeat, and the
later lines go. Nothing is compared with more than the first occurrence, so a common line or passage gives one match per
occurrence. Any thinning of the windows would lose runs of the least length.

Only fingerprints and places move, neither texts nor lines. A fingerprint of over a thousandth of all, of which there
are less than a thousand, is sent to every task.

Defined results: lines are cut at line feeds and compared after trimming blanks, tabs and carriage
returns; lines without a word are blank: runs go on across them as if they were not there, and they are never
removed; null texts have no line; within one document a repeat loses the later lines, overlapping occurrences included;
rows that repeat a key are documents of their own, in the order of their texts' hashes; rows equal in key and text
are one occurrence, and what goes from one goes from all; a null key sorts after all others; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

WINDOW, MIN_WORDS, LONG_WORDS = 2, 20, 25
#: A fingerprint of over one in ``HOT`` places is hot.
HOT = 1000


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _words(line: Column) -> Column:
    return F.size(F.regexp_extract_all(line, F.lit(f"({common.WORD})"), F.lit(1)))


def hashes_of(lines: Column) -> Column:
    """Hash of each trimmed line; blank lines are null."""
    return F.transform(lines, lambda x: F.when(F.trim(x, F.lit(" \t\r")) != "", F.xxhash64(F.trim(x, F.lit(" \t\r")))))


def _ends(window: int, min_words: int, long_words: int) -> Column:
    """For each place of the array ``w`` of words a line, where the shortest passage that begins there ends; null if none counts."""

    def counts(x: Column) -> Column:
        return ((x["n"] >= window) | x["long"]) & (x["words"] >= min_words)

    def longer(x: Column, words: Column) -> Column:
        more = F.struct((x["n"] + 1).alias("n"), (x["words"] + words).alias("words"), (x["long"] | (words >= long_words)).alias("long"))
        return F.when(counts(x), x).otherwise(more)

    none = F.struct(F.lit(0).alias("n"), F.lit(0).alias("words"), F.lit(False).alias("long"))
    # Every line has a word, so no passage needs more lines than this.
    most = max(window, min_words, 1)
    return F.transform("w", lambda _, i: F.aggregate(F.slice("w", i + 1, most), none, longer, lambda x: F.when(counts(x), i + x["n"])))


def _passages() -> Column:
    """(lo, hi) of the least passages, from their ``ends``: the shortest from lo, and the shortest to each hi before the next one's end."""

    def of(end: Column, i: Column) -> Column:
        last = F.greatest(end, F.coalesce(F.get("ends", i + 1), F.size("ends") + 1) - 1)
        return F.when(end.isNotNull(), F.transform(F.sequence(end, last), lambda hi: F.struct(i.alias("lo"), hi.alias("hi"))))

    return F.flatten(F.array_compact(F.transform("ends", of)))


@common.cleaned
def repeated_runs(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, min_words: int = MIN_WORDS, long_words: int = LONG_WORDS) -> DataFrame:
    """Passages to remove: key, lo, hi (lines from lo, before hi, without blank ones) and the first occurrence they repeat."""
    lines = docs.select(_row(key, text).alias("id"), lines_of(F.col(text)).alias("l"))
    each = F.transform("l", lambda x, i: F.struct(_words(x).alias("w"), i.alias("p")))
    full = lines.select("id", hashes_of(F.col("l")).alias("all"), F.filter(each, lambda x: x["w"] > 0).alias("x"))
    base = full.select("id", "all", F.col("x.w").alias("w"), F.col("x.p").alias("p")).withColumn("h", F.transform("p", lambda i: F.get("all", i)))
    least = base.select("id", "h", "p", _ends(window, min_words, long_words).alias("ends"))
    prints = least.select("id", "h", "p", F.explode(_passages()).alias("at"))
    lo, hi = F.col("at.lo"), F.col("at.hi")
    passage = F.slice("h", lo + 1, hi - lo)
    marks = prints.select("id", F.get("p", lo).alias("lo"), (F.get("p", hi - 1) + 1).alias("hi"), F.xxhash64(passage).alias("f"), F.xxhash64(F.lit(7), passage).alias("g"))
    marks = common.materialise(marks, "marks")
    first = marks.groupBy("f", "g").agg(F.min(F.struct("id", "lo")).alias("s"), F.count(F.lit(1)).alias("n")).where("n > 1")
    first = common.materialise(first.select("f", "g", F.col("s.id").alias("source"), F.col("s.lo").alias("source_lo"), "n"), "firsts")
    total = marks.count()
    hot, few = F.broadcast(first.where(F.col("n") * HOT > total)), first.where(F.col("n") * HOT <= total)
    met = marks.join(hot, ["f", "g"]).unionByName(marks.join(hot, ["f", "g"], "left_anti").join(few, ["f", "g"]))
    later = met.where((F.col("id") != F.col("source")) | (F.col("lo") != F.col("source_lo")))
    return later.select(F.col("id.key").alias(key), F.col("id.mark").alias("mark"), "lo", "hi", F.col("source.key").alias("source"), "source_lo")


def _row(key: str, text: str) -> Column:
    """What a row is told apart by, in the order of documents."""
    return F.struct(F.col(key).isNull().alias("last"), F.col(key).alias("key"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("mark"))


def line_dedup(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """One row per row of ``docs``: key, n_lines, n_removed, kept_text."""
    runs = repeated_runs(docs, key, text, **options)
    gone = runs.groupBy(key, "mark").agg(F.collect_set(F.struct("lo", "hi")).alias("runs")).select(F.col(key).alias("__k"), F.col("mark").alias("__m"), "runs")
    removed = gone.select("__k", "__m", F.array_distinct(F.flatten(F.transform("runs", lambda r: F.sequence(r["lo"], r["hi"] - 1)))).alias("__in"))
    rows = docs.select(_row(key, text).alias("__id"), F.col(text).alias("__t"), lines_of(F.col(text)).alias("__l"))
    same = F.col("__id.key").eqNullSafe(F.col("__k")) & (F.col("__id.mark") == F.col("__m"))
    both = rows.join(removed, same, "left").withColumn("gone", F.filter("__in", lambda i: F.get("__l", i).rlike(common.WORD)))
    # Kept lines in order: positions without the removed ones.
    at = F.array_except(F.sequence(F.lit(0), F.size("__l") - 1), F.coalesce("gone", F.array().cast("array<int>")))
    kept = F.when(F.col("gone").isNull(), F.col("__t")).otherwise(F.array_join(F.transform(at, lambda i: F.get("__l", i)), "\n"))
    return both.select(F.col("__id.key").alias(key), F.when(F.col("__t").isNull(), 0).otherwise(F.size("__l")).cast("long").alias("n_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"), kept.alias("kept_text"))


def op7_line_dedup(spark, sf_dir: str) -> DataFrame:
    found = line_dedup(common.documents(spark, sf_dir))
    return found.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("kept_text", F.lit("")), 256).alias("kept_sha256"))


