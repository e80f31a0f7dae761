"""The sparse index: ranks instead of node numbers, tree presence, directory, packed rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.config import IndexSpec
from tierbit.functions.bits import bits_on
from tierbit.operators.build import KEY


def ranked(masks: DataFrame) -> DataFrame:
    """Rank layout: (level, dim, key, rank, mask), masks of a feature and level in node order.

    Ranks within a tree, and the masks of the trees before it: only one row per tree meets the others of its feature.
    """
    own = ["level", *KEY, "tree"]
    trees = masks.groupBy(*own).agg(F.count("*").alias("n"))
    before = W.partitionBy("level", *KEY).orderBy("tree").rowsBetween(W.unboundedPreceding, -1)
    trees = trees.select(*own, F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    within = masks.withColumn("_in", F.row_number().over(W.partitionBy(*own).orderBy("node")) - 1)
    return within.join(trees, own).withColumn("rank", (F.col("before") + F.col("_in")).cast("int")).drop("before", "_in")


def presence(masks: DataFrame, spec: IndexSpec) -> DataFrame:
    """(dim, key, tree): the trees in which a feature occurs."""
    return masks.where(F.col("level") == spec.h - 1).select(*KEY, F.col("node").alias("tree"))


def presence_bitmaps(masks: DataFrame, spec: IndexSpec) -> DataFrame:
    """The same as Spark bitmaps: 32,768 trees to a row."""
    t = presence(masks, spec)
    return t.groupBy(*KEY, F.expr("bitmap_bucket_number(tree)").alias("bucket")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(tree))").alias("bits"))


def directory(masks: DataFrame, spec: IndexSpec) -> DataFrame:
    """(dim, key, tree, nth, first_middle, first_leaf): ranks of each tree's first masks (three levels).

    Windows run within a feature; for a feature in very many trees, do it per segment and
    add the segments' totals.
    """
    roots = masks.where("level = 2").select(*KEY, "tree", F.bit_count("mask").cast("long").alias("middles"))
    leaves = masks.where("level = 1").groupBy(*KEY, "tree").agg(F.sum(F.bit_count("mask")).alias("leaves"))
    before = W.partitionBy(*KEY).orderBy("tree").rowsBetween(W.unboundedPreceding, -1)
    both = roots.join(leaves, [*KEY, "tree"])
    return both.select(*KEY, "tree", F.count("*").over(before).alias("nth"), F.coalesce(F.sum("middles").over(before), F.lit(0)).alias("first_middle"), F.coalesce(F.sum("leaves").over(before), F.lit(0)).alias("first_leaf"))


def pack(masks: DataFrame, spec: IndexSpec) -> DataFrame:
    """(dim, key, tree, root, middles, leaves): one row per feature and non-empty tree, 1 + b + b*b masks at most."""
    if spec.h != 3:
        raise ValueError("packed rows hold three levels")
    level = lambda n: F.array_sort(F.collect_list(F.when(F.col("level") == n, F.struct("node", "mask"))))
    rows = masks.groupBy(*KEY, "tree").agg(F.bit_or(F.when(F.col("level") == 2, F.col("mask"))).alias("any"), level(1).alias("middles"), level(0).alias("leaves"))
    only = lambda c: F.transform(c, lambda x: x["mask"]).alias(c)
    return rows.select(*KEY, "tree", F.col("any").alias("root"), only("middles"), only("leaves"))


def unpack(packed: DataFrame, spec: IndexSpec) -> DataFrame:
    """Back to keyed rows: node numbers from the bits of the level above."""
    b = spec.b
    roots = packed.select(F.lit(2).alias("level"), *KEY, "tree", F.col("tree").alias("node"), F.col("root").alias("mask"))
    mids = packed.select(*KEY, "tree", F.posexplode(F.arrays_zip(bits_on("root", b).alias("j"), F.col("middles").alias("m"))).alias("i", "x")).select(F.lit(1).alias("level"), *KEY, "tree", (F.col("tree") * b + F.col("x.j")).alias("node"), F.col("x.m").alias("mask"))
    places = F.flatten(F.zip_with(bits_on("root", b), "middles", lambda j, m: F.transform(bits_on(m, b), lambda k: j * b + k)))
    leaves = packed.select(*KEY, "tree", F.explode(F.arrays_zip(places.alias("j"), F.col("leaves").alias("m"))).alias("x")).select(F.lit(0).alias("level"), *KEY, "tree", (F.col("tree") * b * b + F.col("x.j")).alias("node"), F.col("x.m").alias("mask"))
    return roots.unionByName(mids).unionByName(leaves)


def position(tree: Column, middle: Column, leaf: Column, bit: Column, spec: IndexSpec) -> Column:
    b = spec.b
    return tree * spec.tree + middle * b * b + leaf * b + bit


def bounds(masks: DataFrame, spec: IndexSpec, n_records: int, dims: int) -> DataFrame:
    """One row: mask bits by level against the derived limits, and the worst leaf node of a dimension."""
    by = masks.groupBy("level").agg((F.count("*") * spec.b).alias("bits"))
    total = masks.agg((F.count("*") * spec.b).alias("total_bits"))
    worst = masks.where("level = 0").groupBy("dim", "node").count().agg(F.max("count").alias("leaf_rank"))
    top = by.agg(F.max("bits").alias("largest_level"))
    return total.crossJoin(worst).crossJoin(top).select("total_bits", "leaf_rank", "largest_level", F.lit(3 * spec.b * dims * n_records).cast("long").alias("bound_bits"), (F.col("total_bits") <= 3 * spec.b * dims * n_records).alias("within"), (F.col("leaf_rank") <= spec.b).alias("rank_within"))
