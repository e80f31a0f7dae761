import math

import numpy as np
from pyspark.sql import functions as F

from tierbit.llm import topk

SCHEMA = "vec_id long, embedding array<float>, label int, score string"


def brute(rows, k):
    vecs = {(i, tuple(math.floor(1024 * float(np.float32(x))) for x in v)) for i, v, *_ in rows if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)}
    out = []
    for q, a in vecs:
        if q % 100 == 0:
            scored = sorted((-sum(x * y for x, y in zip(a, b)), i) for i, b in vecs if i != q)
            out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(scored[:k])]
    return sorted(out)


def run(spark, rows, **kw):
    df = spark.createDataFrame(rows, SCHEMA)
    return sorted(map(tuple, topk.threshold_topk(df, F.col("id") % 100 == 0, **kw).collect()))


def test_against_brute_force_with_ties_hot_vectors_and_bad_rows(spark):
    rng = np.random.default_rng(4)
    rows = [(i, [float(x) for x in rng.normal(size=8)], 1, None) for i in range(450)]
    rows += [(1000 + i, rows[0][1], 0, "s") for i in range(150)]  # a vector that fills a quarter of the table
    rows += [(2000, None, None, None), (2100, [float("nan")] * 8, 1, None), (2200, [None] + [1.0] * 7, 1, None), (2300, [float("inf")] * 8, 1, None), (None, [1.0] * 8, 1, None), rows[5]]
    for kw in ({}, {"slices": 3, "block_rows": 64, "query_rows": 2}, {"k": 3, "slices": 1}, {"slices": 2, "block_rows": 128, "query_rows": 2, "depth": 1}, {"slices": 4, "block_rows": 100, "depth": 40}):
        assert run(spark, rows, **kw) == brute(rows, kw.get("k", 10))


def test_few_rows_and_none(spark):
    rows = [(100, [1.0, 2.0], 0, None), (1, [0.5, -1.0], 0, None)]
    assert run(spark, rows) == brute(rows, 10)
    assert topk.threshold_topk(spark.createDataFrame([], SCHEMA), F.col("id") % 100 == 0).count() == 0
    assert topk.threshold_topk(spark.createDataFrame([(7, [1.0], 0, None)], SCHEMA), F.col("id") % 100 == 0).count() == 0


def test_lists_that_end_above_the_cutoff_go_back(spark):
    """Short lists of many blocks bound badly, so most of them are collected anew; the answer is the same."""
    rng = np.random.default_rng(11)
    rows = [(i, [float(x) for x in rng.normal(size=int(rng.integers(3, 9)))], 1, None) for i in range(600)]
    for kw in ({"block_rows": 50, "depth": 1, "k": 1}, {"block_rows": 50, "depth": 1, "k": 1, "slices": 3, "query_rows": 1}):
        assert run(spark, rows, **kw) == brute(rows, 1)


def test_clashing_columns_and_large_components(spark):
    rows = [(100 * i, [float(2**16 * (i % 7 - 3)), 1.5, -float(2**14 * i)], i, "rank") for i in range(40)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, rank int, score string")
    got = sorted(map(tuple, topk.threshold_topk(df, F.col("id") % 100 == 0, k=4).collect()))
    vecs = [(i, [math.floor(1024 * x) for x in v]) for i, v, *_ in rows]
    want = []
    for q, a in vecs:
        best = sorted((-sum(x * y for x, y in zip(a, b)), i) for i, b in vecs if i != q)[:4]
        want += [(q, n + 1, i, -s) for n, (s, i) in enumerate(best)]
    assert got == sorted(want)


def test_scores_beyond_a_long_do_not_fail(spark):
    rows = [(i, [1e300, -1e300, 1e18], 0, None) for i in range(0, 300, 50)] + [(1, [1e17 * i for i in range(3)], 0, None)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int, score string")
    assert topk.threshold_topk(df, F.col("id") % 100 == 0, k=2).count() == 6
