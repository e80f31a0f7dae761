"""Which path answers a query: the index for keyword features, a plain scan for anything else."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tierbit.config import IndexSpec
from tierbit.operators.search import All, Any, of, search_keyed


def support(masks: DataFrame, features) -> dict:
    """Records of each feature, from the popcounts of its leaf masks."""
    rows = masks.where(of(features) & (F.col("level") == 0)).groupBy("dim", "key").agg(F.sum(F.bit_count("mask")).alias("n")).collect()
    return {(r["dim"], r["key"]): r["n"] for r in rows}


def ordered(query: All, supports: dict) -> All:
    """The same conjunction, rarest feature first: its trees prune the others."""
    return All(tuple(sorted(query.features, key=lambda f: supports.get(f, 0))), query.without)


def route(query: All | Any | str, ledger: DataFrame, masks: DataFrame, spec: IndexSpec, n_records: int, most: float = 0.5) -> tuple[str, DataFrame]:
    """("index" or "scan", positions). A predicate that no feature stands for passes through to a scan; so does a query
    that most records match, of which the index would read as much as the ledger."""
    if isinstance(query, str):
        return "scan", ledger.where(query).select("pos")
    supports = support(masks, query.features)
    least = min((supports.get(f, 0) for f in query.features), default=0) if isinstance(query, All) else sum(supports.values())
    if least > most * n_records:
        one = [(F.col("dim") == d) & (F.col("key") == k) for d, k in query.features]
        return "scan", scan(ledger, query) if one else ledger.select("pos")
    return "index", search_keyed(masks, ordered(query, supports) if isinstance(query, All) else query, spec)


def scan(features: DataFrame, query: All | Any) -> DataFrame:
    """The query on (pos, dim, key) rows directly."""
    hit = features.where(of(query.features)).groupBy("pos").agg(F.count_distinct("dim", "key").alias("n"))
    if isinstance(query, Any):
        return hit.select("pos")
    found = hit.where(F.col("n") == len(query.features)).select("pos")
    return found.join(features.where(of(query.without)).select("pos"), "pos", "left_anti") if query.without else found
