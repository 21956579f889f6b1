"""A corpus pipeline of five stages, each one of the training-data operators.

Language identification rejects texts without a language, the n-gram join keeps one document of each near-duplicate
class, substring dedup cuts repeated passages, mixing turns rates into copies, and byte-level BPE encodes what is left.
Each stage's rows are written as Parquet and read again as the next one's documents; the rows before them then go.

All stages take null and empty texts, repeated rows and empty tables; texts are taken whole, however long. Extra columns stay until the
last stage; names with two leading underscores are reserved.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mmquery.llm import byte_bpe, common, language_id, mixing, ngram_join, substring_dedup


def identify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a recognised language, however sure; only null texts and texts without a letter go.

    The model is fitted on the stage's own input (labels of documents not held out); the columns stay as they are.
    """
    model = language_id.learn(docs)
    keep = language_id.predict(docs, model)
    if not model.languages:  # nothing to learn from: nothing can be recognised or rejected
        return docs
    return keep.where(F.col("__lang") != language_id.UNKNOWN).select(*docs.columns)


def deduplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates, that of the least doc_id; documents without words all stay, rows alike in id and text are one."""
    return ngram_join.keep_one(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without repeated windows; n_chars follows. Texts that lose nothing, null ones too, stay as they are, to the byte; no row goes."""
    out = substring_dedup.remove_repeats(docs, joined=False)
    n_chars = F.when(F.col("__n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return out.select(*[n_chars.alias(c) if c == "n_chars" else F.col(c) for c in docs.columns])


def balance(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it: copies are rows. Documents without words are taken once; an unwanted document goes."""
    out = mixing.mix(docs)
    return out.where("__copies > 0").withColumn("__copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__copies")))).select(*docs.columns)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and ids of every row; a null or empty text has none."""
    return byte_bpe.encode(docs)


STAGES = [("language_id", identify), ("ngram_join", deduplicate), ("substring_dedup", cut_repeats), ("mixing", balance), ("byte_bpe", encode)]

#: Piece models, entropy balancing and byte pairs can't be said in SQL; tests hold run() against brute-force stages.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        before, docs = docs, common.materialise(stage(spark, docs, sf_dir), f"stage-{name}")
        if i:
            common.discard(before)
    return docs
