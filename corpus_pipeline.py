"""From raw documents to packed training sequences, in four stages.

Each stage is a function (spark, docs, sf_dir) -> DataFrame; its result is written as Parquet
and read again as the next stage's documents. All but the last return the columns they were given.

1. quality: documents that the classifier rejects go; it learns from the labels of ``sf_dir``.
2. near_duplicates: of each group of near-duplicates (five-word shingles, similarity 0.8 or more)
   the document with the smallest identifier stays. Documents without words, and rows with a null
   identifier, are no one's duplicates; texts that share an identifier are documents of their own.
3. mixing: each document stays, and documents of rarer sources occur again, up to twice.
4. packing: one row per piece of a document in a sequence of at most 4096 tokens.

Rows that repeat an identifier and its text are one document after stage 2. An empty table passes
through all stages as an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.llm.chosen_path import near_duplicates
from patchspace.llm.mixing import apply_mix
from patchspace.llm.packing import pack
from patchspace.llm.quality import THRESHOLD, fit, scorer
from patchspace.shared import staged

WORDS, PERCENT, MAX_REPEATS = 5, 80, 2.0
MOST_SENT = 1_000_000  # keys of removed rows, 16 bytes each, that may go to every task


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return docs.where(scorer(model)(F.col("text")) >= THRESHOLD)


def near_duplicate_removal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows are told apart by identifier and text, so other texts of an identifier stay."""
    classes = staged(near_duplicates(docs, WORDS, PERCENT), "pipeline-classes")
    gone = staged(classes.where("NOT first").select(F.col("doc_id").alias("g_id"), F.col("text_key").alias("g_key")).distinct(), "pipeline-gone")
    text_key = F.xxhash64(F.coalesce(F.col("text"), F.lit("")))
    rows = docs.select(F.struct(*docs.columns).alias("r"), F.col("doc_id").cast("long").alias("k_id"), text_key.alias("k_key"))
    few = F.broadcast(gone) if gone.count() <= MOST_SENT else gone  # beyond it texts are shuffled once
    kept = rows.join(few, (F.col("k_id") == F.col("g_id")) & (F.col("k_key") == F.col("g_key")), "left_anti").select("r.*")
    ids = classes.where("first AND doc_id IS NOT NULL").agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("d")).first()
    return kept.dropDuplicates(["doc_id", "text"]) if ids.n != ids.d else kept


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return apply_mix(docs, max_repeats=MAX_REPEATS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs)


STAGES = [("quality", quality), ("near_duplicates", near_duplicate_removal), ("mixing", mixing), ("packing", packing)]

ORACLE_SQL = None  # classifier, similarity join and packing have no SQL form; tested stage by stage


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
