"""Search: features combined by AND, OR and NOT, over dense, keyed and packed indexes."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.config import IndexSpec
from tierbit.functions.bits import clip_from, explode_bits, positions, rank_before

Feature = tuple[str, str]


@dataclass(frozen=True)
class All:
    features: tuple[Feature, ...]
    without: tuple[Feature, ...] = ()


@dataclass(frozen=True)
class Any:
    features: tuple[Feature, ...]


def of(features) -> F.Column:
    """A condition that reaches the scan as pushed-down comparisons."""
    return reduce(lambda a, b: a | b, [(F.col("dim") == d) & (F.col("key") == k) for d, k in features])


def _clip(level: DataFrame, n: int, start: int, spec: IndexSpec) -> DataFrame:
    """Only what lies at ``start`` or after it: whole nodes pass, the boundary node loses its earlier bits."""
    if not start:
        return level
    node, child = start // spec.span(n), start // (spec.span(n) // spec.b) % spec.b
    kept = level.where(F.col("node") >= node)
    return kept.withColumn("mask", F.when(F.col("node") == node, clip_from("mask", str(child), spec.b)).otherwise(F.col("mask"))).where("mask <> 0")


def node_masks(masks: DataFrame, query: All | Any, spec: IndexSpec, start: int = 0) -> list[DataFrame]:
    """(node, mask) of the combined query on each level, the root's first; each level reads only surviving nodes."""
    feats = query.features
    own = masks.where(of(feats)).where(F.col("tree") >= start // spec.tree)
    out, above = [], None
    for n in range(spec.h - 1, -1, -1):
        level = own.where(F.col("level") == n)
        if above is not None:
            level = level.join(above, "node", "left_semi")
        if isinstance(query, Any):
            level = level.groupBy("node").agg(F.bit_or("mask").alias("mask"))
        elif len(feats) == 1:
            level = level.select("node", "mask")
        else:
            level = level.groupBy("node").agg(F.bit_and("mask").alias("mask"), F.count("*").alias("n")).where((F.col("n") == len(feats)) & (F.col("mask") != 0)).select("node", "mask")
        level = _clip(level, n, start, spec)
        out.append(level)
        above = explode_bits(level, "mask", spec.b).select((F.col("node") * spec.b + F.col("bit")).alias("node"))
    return out


def search_keyed(masks: DataFrame, query: All | Any, spec: IndexSpec, start: int = 0) -> DataFrame:
    """pos of all matching records from ``start`` on."""
    leaves = node_masks(masks, query, spec, start)[-1]
    if isinstance(query, All) and query.without:
        off = masks.where(of(query.without) & (F.col("level") == 0)).groupBy("node").agg(F.bit_or("mask").alias("off"))
        leaves = leaves.join(off, "node", "left").withColumn("mask", F.expr("mask & ~coalesce(off, 0L)")).where("mask <> 0")
    return positions(leaves, "mask", "node", spec.b).select("pos")


def complement(masks: DataFrame, features: tuple[Feature, ...], n_records: int, spec: IndexSpec) -> DataFrame:
    """pos of the records with none of the features: leaf masks negated within the ledger's length."""
    nodes = masks.sparkSession.range(-(-n_records // spec.b)).withColumnRenamed("id", "node")
    off = masks.where(of(features) & (F.col("level") == 0)).groupBy("node").agg(F.bit_or("mask").alias("off"))
    ones = F.lit((1 << spec.b) - 1 if spec.b < 64 else -1)
    left = nodes.join(off, "node", "left").withColumn("mask", ones.bitwiseAND(F.bitwise_not(F.coalesce("off", F.lit(0).cast("long")))))
    return positions(left, "mask", "node", spec.b).where(F.col("pos") < n_records).select("pos")


def search_dense(dense: DataFrame, feature: Feature, spec: IndexSpec, start: int = 0) -> DataFrame:
    """Top-down by arithmetic: child j of node n is node n * b + j, read by an equality on its number."""
    own = dense.where(of([feature]))
    level = own.where((F.col("level") == spec.h - 1) & (F.col("mask") != 0)).select("node", "mask")
    level = _clip(level, spec.h - 1, start, spec)
    for n in range(spec.h - 2, -1, -1):
        wanted = explode_bits(level, "mask", spec.b).select((F.col("node") * spec.b + F.col("bit")).alias("node"))
        level = _clip(own.where(F.col("level") == n).select("node", "mask").join(wanted, "node"), n, start, spec)
    return positions(level, "mask", "node", spec.b).select("pos")


def search_packed(packed: DataFrame, features: list[Feature], spec: IndexSpec, start: int = 0) -> DataFrame:
    """Conjunction on packed rows: one join per feature on the tree, then masks addressed by rank within the row."""
    b, sides = spec.b, []
    for i, f in enumerate(features):
        own = packed.where(of([f])).where(F.col("tree") >= start // spec.tree)
        starts = F.transform(F.sequence(F.lit(0), F.size("middles") - 1), lambda n: F.aggregate(F.slice("middles", 1, n), F.lit(0), lambda a, m: a + F.bit_count(m)))
        sides.append(own.select("tree", F.col("root").alias(f"r{i}"), F.col("middles").alias(f"m{i}"), F.col("leaves").alias(f"l{i}"), starts.alias(f"s{i}")))
    rows = reduce(lambda a, c: a.join(c, "tree"), sides)
    n = range(len(features))
    both = lambda names: " & ".join(names)
    rows = rows.withColumn("mask", F.expr(both([f"r{i}" for i in n]))).where("mask <> 0")
    rows = explode_bits(rows, "mask", b, "j")
    for i in n:
        at = rank_before(f"r{i}", "j", b)
        rows = rows.withColumn(f"at{i}", at).withColumn(f"mm{i}", F.expr(f"m{i}[at{i}]"))
    rows = rows.withColumn("mask", F.expr(both([f"mm{i}" for i in n]))).where("mask <> 0")
    rows = explode_bits(rows, "mask", b, "k")
    for i in n:
        rows = rows.withColumn(f"lk{i}", rank_before(f"mm{i}", "k", b)).withColumn(f"ll{i}", F.expr(f"l{i}[s{i}[at{i}] + lk{i}]"))
    rows = rows.select("tree", "j", "k", F.expr(both([f"ll{i}" for i in n])).alias("mask")).where("mask <> 0")
    rows = rows.withColumn("node", F.col("tree") * b * b + F.col("j") * b + F.col("k"))
    found = positions(rows, "mask", "node", b).select("pos")
    return found.where(F.col("pos") >= start) if start else found


def count(masks: DataFrame, query: All | Any, spec: IndexSpec, start: int = 0) -> DataFrame:
    """How many records match, without naming them."""
    return node_masks(masks, query, spec, start)[-1].agg(F.coalesce(F.sum(F.bit_count("mask")), F.lit(0)).alias("n"))


def masks_read(masks: DataFrame, query: All | Any, spec: IndexSpec, start: int = 0) -> DataFrame:
    """level, masks_read: masks that the search loads, each feature's counted."""
    own = masks.where(of(query.features)).where(F.col("tree") >= start // spec.tree)
    levels, out = node_masks(masks, query, spec, start), None
    for i, n in enumerate(range(spec.h - 1, -1, -1)):
        level = own.where(F.col("level") == n)
        if start:
            level = level.where(F.col("node") >= start // spec.span(n))
        if i:
            wanted = explode_bits(levels[i - 1], "mask", spec.b).select((F.col("node") * spec.b + F.col("bit")).alias("node"))
            level = level.join(wanted, "node", "left_semi")
        one = level.agg(F.lit(n).alias("level"), F.count("*").alias("masks_read"))
        out = one if out is None else out.unionByName(one)
    return out


def fetch(ledger: DataFrame, found: DataFrame) -> DataFrame:
    """Rows (or digests) at the positions; Spark broadcasts the positions if their size allows."""
    return ledger.join(found, "pos", "left_semi")


def gaps(found: DataFrame) -> DataFrame:
    """pos as distance from the hit before it (the first: from zero), numbered; for inspection of one answer."""
    order = W.orderBy("pos")
    return found.select(F.row_number().over(order).alias("nth"), (F.col("pos") - F.lag("pos", 1, 0).over(order)).alias("gap"))


def from_gaps(g: DataFrame) -> DataFrame:
    return g.select(F.sum("gap").over(W.orderBy("nth")).alias("pos"))
