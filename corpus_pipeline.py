"""From raw documents to packed training sequences.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir) and returns the documents
that the next stage works on; the last returns the packed pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewmap.llm import common, exactdedup, langid, mixing, packing, setjoin
from skewmap.session import ship

#: The language model and the near-duplicate join have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def _ready(spark: SparkSession) -> None:
    """Workers get the package, and they and the driver give up what the stage before, which is written by now, left with them."""
    ship(spark)
    common.release()
    common.give_back()


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told stay; those without letters go."""
    _ready(spark)
    held = F.coalesce(common.residue("doc_id", 5) == 0, F.lit(False))
    model = langid.LanguageIdentifier.fit(docs.where(~held))
    return docs.where(model.predict(F.col("text"))["lang_pred"] != "und")


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts stays."""
    _ready(spark)
    return exactdedup.exact_dedup(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays: the one of smallest doc_id."""
    _ready(spark)
    return setjoin.near_dedup(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources mixed to their targets; a document may stand twice."""
    _ready(spark)
    return mixing.mixed_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents cut and packed into sequences of at most 2048 tokens."""
    _ready(spark)
    return packing.pack(docs)


STAGES = [
    ("language_id", language_stage),
    ("exact_dedup", exact_stage),
    ("ngram_jaccard_join", near_stage),
    ("mixing", mixing_stage),
    ("best_fit_packing", packing_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = common.materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
