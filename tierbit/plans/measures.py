"""Measures: counted costs as DataFrames, latencies as driver-side timings."""

from __future__ import annotations

import statistics
import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tierbit.config import IndexSpec


def time_query(make, runs: int = 5, cold: bool = True) -> dict[str, float]:
    """Milliseconds of writing the result nowhere: first, mean and median."""
    took = []
    for _ in range(runs):
        df = make()
        if cold:
            df.sparkSession.catalog.clearCache()
        start = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        took.append(1000 * (time.perf_counter() - start))
    return {"first_ms": took[0], "mean_ms": statistics.fmean(took), "median_ms": statistics.median(took)}


def time_insert(action, runs: int = 3) -> float:
    """Mean milliseconds of an append with its writes."""
    took = []
    for i in range(runs):
        start = time.perf_counter()
        action(i)
        took.append(1000 * (time.perf_counter() - start))
    return statistics.fmean(took)


def read_amplification(found: DataFrame, page_rows: int) -> DataFrame:
    """hits, pages, rows_per_hit: rows in the touched pages for every hit."""
    pages = found.agg(F.count("*").alias("hits"), F.count_distinct(F.expr(f"pos div {page_rows}")).alias("pages"))
    return pages.withColumn("rows_per_hit", F.round(F.when(F.col("hits") > 0, F.col("pages") * page_rows / F.col("hits")), 6))


def index_size(masks: DataFrame, spec: IndexSpec) -> DataFrame:
    """dim, level, masks, bits."""
    return masks.groupBy("dim", "level").agg(F.count("*").alias("masks"), (F.count("*") * spec.b).alias("bits"))


def dense_bits(features: int, n: int, spec: IndexSpec) -> int:
    """Bits of the dense form: every node of every level for every feature."""
    return features * sum(-(-n // spec.span(level)) for level in range(spec.h)) * spec.b


def filter_bits(n: int, spec: IndexSpec) -> int:
    """Presence bits per feature."""
    return -(-n // spec.tree)


def feature_stats(pf: DataFrame) -> DataFrame:
    return pf.groupBy("dim").agg(F.count_distinct("key").alias("features"))


def recall_precision(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: missing and extra positions (both 0 for an exact search)."""
    missing = truth.exceptAll(found).agg(F.count("*").alias("missing"))
    return missing.crossJoin(found.exceptAll(truth).agg(F.count("*").alias("extra")))


def side_by_side(ledger: DataFrame, found: DataFrame, n: int, hit: str, below: str, spec: IndexSpec, resumed: bool, fanout: int = 256) -> DataFrame:
    """size, method, measure, value for seven prefixes in one pass over the ledger and one over the hits (pos) that the index found.

    ``resumed`` asks for the last tenth of each prefix. ours: hits, and masks that a search loads;
    ordered: leaf pages of the matching run, which can't skip old entries; composite: entries from the sought
    leaf on; skip list: nodes walked after the seek; full scan: rows.
    """
    sizes = F.array(*[F.struct(F.lit(s).cast("long").alias("size"), F.lit(s * 9 // 10 if resumed else 0).cast("long").alias("s")) for s in prefixes(n)])
    per = lambda df, *cols: df.select("pos", *cols, F.explode(sizes).alias("x")).select("pos", *[c for c in ("hit", "below") if c in df.columns], "x.size", "x.s").where("pos < size")
    rows = per(ledger.select("pos", F.expr(hit).alias("hit"), F.expr(below).alias("below")), "hit", "below")
    leaf = lambda c: F.expr(f"{c} div {fanout}")
    counts = rows.groupBy("size").agg(F.count_if("hit").alias("all_hits"), F.count_if("below").alias("below"), F.count_if(leaf("pos") >= leaf("s")).alias("scanned"), F.count_if(F.col("pos") >= F.col("s")).alias("fresh"))
    spans = [spec.span(level) for level in range(spec.h)]
    nodes = reduce(lambda a, b: a + b, [F.count_distinct(F.expr(f"if(pos div {x} >= s div {x}, pos div {x}, null)")) for x in spans])
    ours = per(found).groupBy("size").agg(F.count_if(F.col("pos") >= F.col("s")).alias("hits"), nodes.alias("masks"))
    both = counts.join(ours, "size", "left")
    pages = F.when(F.col("all_hits") == 0, 0).otherwise(F.expr(f"(below + all_hits - 1) div {fanout} - below div {fanout} + 1"))
    out = [("ours", "hits", F.coalesce("hits", F.lit(0))), ("ours", "masks_read", F.coalesce("masks", F.lit(0))), ("ordered", "leaf_pages", pages), ("composite", "scanned", F.col("scanned")), ("skip list", "walked", F.col("fresh")), ("full scan", "rows", F.col("size"))]
    line = F.array(*[F.struct(F.lit(m).alias("method"), F.lit(x).alias("measure"), v.cast("double").alias("value")) for m, x, v in out])
    return both.select("size", F.explode(line).alias("o")).select("size", "o.*")


def prefixes(n: int, steps: int = 7) -> list[int]:
    return [i * n // steps for i in range(1, steps + 1)]
