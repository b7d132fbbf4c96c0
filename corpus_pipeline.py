"""Documents to packed training sequences: language ID, line deduplication, near duplicates, mixing, packing.

Each stage takes what its predecessor kept, as a table that was written and read again; all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from curvebalance.llm import common, jaccard_join, language_id, line_dedup, mixing, packing, tokens


#: Columns that stages read or write; all others pass through them under private names, so none clashes with a stage's own.
USED = ("doc_id", "text", "lang", "source", "n_chars")
#: The share of a document's letters that must be in words of scripts that learned languages use.
LEAST_SHARE = 0.5


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents of which learned languages together may have half the letters at least; a null lang becomes that of most letters. So texts without
    letters go, and those mostly in scripts that no learned language uses; mixtures of learned languages stay. Learns from the labelled rows of its input."""
    docs, names = common.apart(docs, USED)
    model = language_id.train(docs)
    if not model.langs:  # nothing to learn from: only texts without letters are rejected
        return common.restored(docs.where(F.col("text").rlike(r"\p{L}")), names)
    found = language_id.predict(docs, model, learned=True).where((F.col("lang_pred") != "und") & (F.col("learned") >= LEAST_SHARE))
    return common.restored(found.withColumn("lang", F.coalesce("lang", "lang_pred")), names)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes lines that an earlier line repeats, exactly or within one word; documents of which nothing is left go."""
    docs, names = common.apart(docs, USED)
    left = line_dedup.dedup(docs, least_words=1)
    left = left.where((F.size("dropped") == 0) | F.coalesce(F.col("text").rlike(r"\S"), F.lit(False)))
    if "n_chars" in docs.columns:
        kind = docs.schema["n_chars"].dataType
        left = left.withColumn("n_chars", F.when(F.size("dropped") > 0, F.length("text").cast(kind)).otherwise(F.col("n_chars")))
    return common.restored(left, names)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document, that of the smallest id, of each group of near duplicates."""
    docs, names = common.apart(docs, USED)
    return common.restored(jaccard_join.keep_one(docs, words=5, num=80, den=100), names)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats documents so that sources have their target weights; every document is there once at least."""
    docs, names = common.apart(docs, USED)
    return common.restored(mixing.mix(docs, entropy=0.95, most_epochs=2.0), names)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all documents into sequences of 2048 tokens."""
    return packing.pack_documents(docs, tokens.vocabulary("byte_bpe_50k.json"), tokens.vocabulary("byte_bpe_50k.tiktoken"), capacity=2048, end_id=0)


STAGES = [("language id", language), ("line dedup", lines), ("n-gram jaccard join", near_duplicates), ("mixing", mixture), ("best-fit packing", sequences)]

#: SQL can express none of the stages (the mixture's blocks come from Spark's hash); tests hold each against a brute-force version.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = common.stash(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
