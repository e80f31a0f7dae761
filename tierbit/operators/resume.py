"""Resumable search: tokens, their log, and what lies between two of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.config import IndexSpec
from tierbit.operators.search import All, Any, search_keyed

POS_BITS = 40
LOG = "query_id int, version int, token long, issued_at timestamp"


def make_token(query_id: int, stop: int) -> int:
    """24 bits of query id above 40 bits of stop position, as a signed long."""
    if not 0 <= query_id < 1 << 24 or not 0 <= stop < 1 << POS_BITS:
        raise ValueError("query id or position out of range")
    x = query_id << POS_BITS | stop
    return x - (1 << 64) if x >> 63 else x


def read_token(token: int) -> tuple[int, int]:
    x = token & (1 << 64) - 1
    return x >> POS_BITS, x & (1 << POS_BITS) - 1


def token_columns(token: str) -> tuple[Column, Column]:
    return F.expr(f"cast(shiftrightunsigned({token}, {POS_BITS}) as int)"), F.expr(f"{token} & {(1 << POS_BITS) - 1}L")


def query_number(query: All | Any, ids: dict[str, int]) -> int:
    """The number of a normalised expression; a new one gets the next number."""
    kind = type(query).__name__
    text = kind + repr((tuple(sorted(query.features)), tuple(sorted(getattr(query, "without", ())))))
    return ids.setdefault(text, len(ids))


class TokenLog:
    """Tokens in order of issue; the newest of a query is the one to resume from."""

    def __init__(self, spark: SparkSession, rows: DataFrame | None = None):
        self.spark, self.rows = spark, rows if rows is not None else spark.createDataFrame([], LOG)

    def add(self, query_id: int, token: int, issued_at) -> TokenLog:
        last = self.rows.where(F.col("query_id") == query_id).agg(F.coalesce(F.max("version"), F.lit(0))).first()[0]
        new = self.spark.createDataFrame([(query_id, last + 1, token, issued_at)], LOG)
        return TokenLog(self.spark, self.rows.unionByName(new))

    def latest(self) -> DataFrame:
        order = W.partitionBy("query_id").orderBy(F.desc("version"))
        return self.rows.withColumn("n", F.row_number().over(order)).where("n = 1").drop("n")

    def as_of(self, moment) -> DataFrame:
        return TokenLog(self.spark, self.rows.where(F.col("issued_at") <= F.lit(moment))).latest()

    def stop(self, query_id: int, version: int | None = None) -> int:
        rows = self.latest() if version is None else self.rows.where(F.col("version") == version)
        got = rows.where(F.col("query_id") == query_id).select("token").first()
        return read_token(got[0])[1] if got else 0


def run(masks: DataFrame, query: All | Any, spec: IndexSpec, n_records: int, query_id: int = 0, token: int | None = None) -> tuple[DataFrame, int]:
    """(new positions, new token); the token names the ledger's end, also after an empty answer."""
    start = 0 if token is None else read_token(token)[1]
    return search_keyed(masks, query, spec, start), make_token(query_id, n_records)


def between(masks: DataFrame, query: All | Any, spec: IndexSpec, first: int, last: int) -> DataFrame:
    """Matches that a search at token ``first`` missed and one at token ``last`` had: a lost fragment, or a rollback."""
    a, b = read_token(first)[1], read_token(last)[1]
    return search_keyed(masks.where(F.col("tree") <= max(b - 1, 0) // spec.tree), query, spec, a).where(F.col("pos") < b)
