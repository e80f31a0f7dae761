"""A corpus pipeline over documents: language, exact copies, near copies, mixing, packing.

Every stage takes (spark, docs, sf_dir) and reads all that its predecessor kept. All but
the last return the columns of documents. Rows may hold nulls anywhere; of rows that
repeat a text one passes the second stage; texts are read whole; columns of any other names
pass as they are; an empty table passes through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tierbit.llm import exactdedup, langid, mixing, neardup, packing
from tierbit.llm.common import drop_rows, id_crc, stored, table
from tierbit.llm.queries import tokenizer_path


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of no language (null or without a letter) go, whatever the model predicts for the others."""
    model = langid.fit(docs, F.coalesce(id_crc() % 3 != 1, F.lit(True)))
    if not model.classes:  # the same rule
        return docs.where(F.col("text").rlike(r"\p{L}"))
    wrapped = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), "text")
    return langid.identify(wrapped, model).where("lang_pred <> 'und'").select("row.*")


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest doc_id stays, one of rows that repeat it."""
    return exactdedup.survivors(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the least doc_id stays."""
    return drop_rows(docs, neardup.near_duplicates(docs).where("not kept").select("doc_id", "tag"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sampled so that expected tokens approach the target shares of source, language and topic."""
    return mixing.mixed(docs, mixing.Mix(budget=0.8), carry=True).where("copies > 0").select("row.*")


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences with their place in windows of 2048."""
    return packing.pack(docs, tokenizer_path("byte_bpe_50k.json"), end_id=1, window=2048)


STAGES = [("language", language), ("exact_dedup", exact), ("near_dedup", near), ("mixing", mix), ("packing", pack)]
#: Learned predictions and signatures have no SQL form; tests hold each stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
