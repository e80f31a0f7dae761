"""Building the index: masks by level, from features of records."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tierbit.config import IndexSpec
from tierbit.functions.bits import one_bit

KEY = ["dim", "key"]


def leaf_masks(pf: DataFrame, spec: IndexSpec) -> DataFrame:
    """(dim, key, tree, node, mask) of level 0: a partial OR before the exchange, a final one after."""
    return pf.groupBy(*KEY, F.expr(f"pos div {spec.tree}").alias("tree"), F.expr(f"pos div {spec.b}").alias("node")).agg(F.bit_or(one_bit(f"pos % {spec.b}", spec.b)).alias("mask"))


def lift(masks: DataFrame, spec: IndexSpec) -> DataFrame:
    """The level above: one bit per child that isn't empty."""
    return masks.groupBy(*KEY, "tree", F.expr(f"node div {spec.b}").alias("up")).agg(F.bit_or(one_bit(f"node % {spec.b}", spec.b)).alias("mask")).select(*KEY, "tree", F.col("up").alias("node"), "mask")


def keyed(pf: DataFrame, spec: IndexSpec, cluster_first: bool = False) -> DataFrame:
    """All levels as rows (level, dim, key, tree, node, mask); zero masks never appear.

    ``cluster_first`` ships records once, by feature and tree, and needs no exchange after;
    otherwise masks are combined before they are shipped, which pays for frequent keys.
    """
    if cluster_first:
        pf = pf.withColumn("tree", F.expr(f"pos div {spec.tree}")).repartition(*KEY, "tree")
        level = pf.groupBy(*KEY, "tree", F.expr(f"pos div {spec.b}").alias("node")).agg(F.bit_or(one_bit(f"pos % {spec.b}", spec.b)).alias("mask"))
    else:
        level = leaf_masks(pf, spec)
    out = level.select(F.lit(0).alias("level"), *KEY, "tree", "node", "mask")
    for n in range(1, spec.h):
        level = lift(level, spec)
        out = out.unionByName(level.select(F.lit(n).alias("level"), *KEY, "tree", "node", "mask"))
    return out


def densify(masks: DataFrame, spec: IndexSpec, n_records: int) -> DataFrame:
    """Every mask, empty ones as zero: for few features only (features x records bits)."""
    features = masks.select(*KEY).distinct()
    out = None
    for level in range(spec.h):
        nodes = -(-n_records // spec.span(level))
        grid = features.withColumn("node", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(max(nodes - 1, 0)).cast("long"))))
        full = grid.join(masks.where(F.col("level") == level).select(*KEY, "node", "mask"), [*KEY, "node"], "left").select(F.lit(level).alias("level"), *KEY, F.expr(f"node div {spec.tree // spec.span(level)}").alias("tree"), "node", F.coalesce("mask", F.lit(0)).cast("long").alias("mask"))
        out = full if out is None else out.unionByName(full)
    return out


def merge(old: DataFrame, new: DataFrame) -> DataFrame:
    """OR of two sets of masks: replays and halves of one mask fall together."""
    return old.unionByName(new).groupBy("level", *KEY, "tree", "node").agg(F.bit_or("mask").alias("mask"))


def append(index: DataFrame, batch: DataFrame, spec: IndexSpec, first_pos: int) -> DataFrame:
    """Index after a batch of features from ``first_pos`` on: full trees pass untouched, the open one merges."""
    open_tree = first_pos // spec.tree
    fresh = keyed(batch, spec)
    return index.where(F.col("tree") < open_tree).unionByName(merge(index.where(F.col("tree") >= open_tree), fresh))


def append_stats(index: DataFrame, batch: DataFrame, spec: IndexSpec, first_pos: int) -> DataFrame:
    """level, updated, created: masks that an append changes and adds."""
    tail = index.where(F.col("tree") >= first_pos // spec.tree).withColumnRenamed("mask", "old")
    delta = keyed(batch, spec).join(tail, ["level", *KEY, "tree", "node"], "left")
    return delta.groupBy("level").agg(F.count_if(F.col("old").isNotNull()).alias("updated"), F.count_if(F.col("old").isNull()).alias("created"))


def new_features(index: DataFrame, batch: DataFrame) -> DataFrame:
    """Keys that the index has never seen, with the position they start at: older data stay as they are."""
    return batch.join(index.select(*KEY).distinct(), KEY, "left_anti").groupBy(*KEY).agg(F.min("pos").alias("created_pos"))
