"""Scratch storage and small expressions shared by the training-data operators."""

from __future__ import annotations

import ctypes
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL: list[str] = []


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder below the shared ``spark.checkpoint.dir``.

    Only a local master may go without that setting; it then gets one temporary
    folder per process.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        if not _LOCAL:
            _LOCAL.append("file://" + tempfile.mkdtemp(prefix="tierbit-"))
        base = _LOCAL[0]
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write once and read back: cuts lineage in storage that outlives an executor."""
    path = scratch(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def lean(df: DataFrame, most: int = 4 << 20) -> DataFrame:
    """``df``, of a session that from now on sends Python batches of about ``most`` bytes at most.

    Without a bound a batch is 10,000 rows however long their texts are, held in the JVM and
    in the worker at once. Results don't depend on it; a smaller bound in place is kept.
    """
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    given = df.sparkSession.conf.get(name, None)
    if not (given and given.isdigit() and 0 < int(given) <= most):
        df.sparkSession.conf.set(name, str(most))
    return df


def give_back() -> None:
    """Return what a reused worker freed to the system, where its C library can (it keeps the rest for itself)."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_crc(key: str = "doc_id") -> Column:
    """Unsigned CRC-32 of the id written as text; null for a null id."""
    return F.crc32(F.col(key).cast("string").cast("binary"))


def text_crc(col: str = "text") -> Column:
    return F.crc32(F.encode(F.coalesce(F.col(col), F.lit("")), "UTF-8"))


def without(df: DataFrame, *names: str) -> DataFrame:
    """Drop input columns whose names (in any case) the operator itself returns."""
    taken = {n.lower() for n in names}
    return df.select(*[F.col(f"`{c}`") for c in df.columns if c.lower() not in taken])


def flagged(rows: DataFrame, wanted: DataFrame, cols: list[str], bits: int = 1 << 23) -> DataFrame:
    """``rows`` with ``maybe``: false only if the row's ``cols`` are surely not in ``wanted``.

    A bitmap of fixed size (1 MB for 2**23 bits) is broadcast whatever grows; a fuller one
    says maybe more often, which costs work and no correctness.
    """
    at = F.pmod(F.xxhash64(*cols), F.lit(bits))
    word, bit = F.expr("_at div 64"), F.expr("shiftleft(1L, cast(_at % 64 as int))")
    words = wanted.select(at.alias("_at")).select(word.alias("_word"), bit.alias("_bit")).groupBy("_word").agg(F.bit_or("_bit").alias("_mask"))
    marked = rows.withColumn("_at", at).withColumn("_word", word).join(F.broadcast(words), "_word", "left")
    return marked.withColumn("maybe", F.coalesce(F.expr("shiftright(_mask, cast(_at % 64 as int)) & 1 = 1"), F.lit(False))).drop("_at", "_word", "_mask")


def drop_rows(docs: DataFrame, gone: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the rows whose (id, xxhash64 of text) are in ``gone`` (doc_id, tag).

    Rows that a bitmap rules out never move; only the others meet ``gone`` in a join.
    """
    gone = stored(gone.select("doc_id", "tag").distinct(), "gone")
    wrapped = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.coalesce(F.col(f"`{key}`").cast("long"), F.lit(-1).cast("long")).alias("doc_id"), F.xxhash64(F.col(f"`{text}`")).alias("tag"))
    marked = flagged(wrapped, gone, ["doc_id", "tag"])
    return marked.where("not maybe").select("row").unionByName(marked.where("maybe").join(gone, ["doc_id", "tag"], "left_anti").select("row")).select("row.*")
