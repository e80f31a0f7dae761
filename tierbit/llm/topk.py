"""Exact top-k search by inner product with a three-phase uniform threshold.

Every vector is cut in ``slices`` runs of components. A slice is a node: its tasks see the
components of that slice alone, and the partial inner products there are its score list.
Phase one gathers from each block of a node, per query, the ``depth`` best partial scores
and the least one. A vector's gathered parts, with the node's least part for each that is
missing, bound its score from below; the k-th of these bounds is safe. Phase two sends each
query its cutoff (an equal share of that bound for each node) and collects every part that
reaches it: a vector below the cutoff on all nodes can't be in the answer. A gathered list
that ends below the cutoff is sufficient as it is; only the others go back to their block.
Phase three drops what upper bounds rule out and resolves the rest exactly, in their blocks.
The answer is that of a full scan, ties to the smaller id.

Queries meet vectors in blocks of fixed size, so no task holds either side whole. Equal
vectors are one class: only the k+1 smallest ids of a class can appear in an answer, so
a vector that fills a third of the table is scored once. Vectors that are null or hold a
null or non-finite component, and null ids, take no part; a row repeated whole counts
once; shorter vectors are padded with zeros; an empty table gives no rows. Only the columns
``key`` and ``vec`` are read, so others may have any names. Components are scaled into a
long and saturate there; scores beyond a long are not defined, but don't fail.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.llm.common import stored

LISTS = "qid long, cb long, s int, n long, least long, ids array<long>, part array<long>"
CELLS = 1 << 22  # products held at once in a task


def integer_vectors(df: DataFrame, key: str, vec: str, scale: int = 1024) -> DataFrame:
    good = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return df.where(F.col(key).isNotNull() & F.col(vec).isNotNull() & good).select(F.col(key).cast("long").alias("id"), F.transform(vec, lambda x: F.floor(x.cast("double") * scale).cast("long")).alias("v"))


def _matrix(cells: pd.Series, width: int) -> np.ndarray:
    out = np.zeros((len(cells), width), np.int64)
    for i, x in enumerate(cells):
        out[i, : len(x)] = x
    return out


def _products(q: pd.DataFrame, c: pd.DataFrame) -> Iterator[tuple[int, np.ndarray]]:
    """(first query, its and the next queries' products with all of ``c``), exact: by floats where they hold the sums, else by integers."""
    width = max([1, *map(len, q["v"]), *map(len, c["v"])])
    a, b = _matrix(q["v"], width), _matrix(c["v"], width).T
    small = float(np.abs(a).max()) * float(np.abs(b).max()) * width < 2.0**53
    if small:
        a, b = a.astype(np.float64), b.astype(np.float64)
    step = max(1, CELLS // b.shape[1])
    for i in range(0, len(a), step):
        yield i, (a[i : i + step] @ b).astype(np.int64)


def _known(ids: np.ndarray, part: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids listed by any node, which node lists which, and the parts."""
    every, at = np.unique(np.concatenate(ids), return_inverse=True)
    got, value = np.zeros((len(ids), len(every)), bool), np.zeros((len(ids), len(every)), np.int64)
    ends = np.cumsum([0, *map(len, ids)])
    for s, p in enumerate(part):
        got[s, at[ends[s] : ends[s + 1]]] = True
        value[s, at[ends[s] : ends[s + 1]]] = p
    return every, got, value


def threshold_topk(vectors: DataFrame, queries: Column, k: int = 10, slices: int = 2, block_rows: int = 8192, query_rows: int = 16384, depth: int | None = None, key: str = "vec_id", vec: str = "embedding", scale: int = 1024) -> DataFrame:
    """query_id, rank, vec_id, score; ``queries`` is a condition on column ``id``.

    ``depth`` sets the length of a block's list (a 32nd of the block by default), which
    decides how many lists go back to their block, never the answer.
    """
    spark, want = vectors.sparkSession, k + 1
    depth = max(want, block_rows // 32 if depth is None else depth)
    rows = integer_vectors(vectors, key, vec, scale).distinct()
    near = W.partitionBy("v").orderBy("id")
    classes = stored(rows.withColumn("n", F.row_number().over(near)).where(F.col("n") <= want).groupBy("v").agg(F.sort_array(F.collect_list("id")).alias("ids")).select(F.element_at("ids", 1).alias("cid"), "ids", "v"), "classes")
    asked = stored(rows.where(queries).join(classes.select("cid", "v"), "v").select(F.col("id").alias("query_id"), F.col("cid").alias("qid"), "v"), "asked")
    n_c, width = classes.agg(F.count("*"), F.max(F.size("v"))).first()
    n_q = asked.select("qid").distinct().count()
    if not n_q:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    blocks, q_blocks = -(-n_c // block_rows), -(-n_q // query_rows)
    run = max(1, -(-width // slices))  # components of a slice
    numbers = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    sliced = lambda df: df.withColumn("s", numbers(slices)).withColumn("s", F.col("s").cast("int")).withColumn("v", F.expr(f"slice(v, s * {run} + 1, {run})"))
    held = classes.withColumn("cb", F.pmod(F.xxhash64("cid"), F.lit(blocks)))
    q_rows = stored(asked.groupBy("qid").agg(F.first("v").alias("v")).withColumn("qb", F.pmod(F.xxhash64("qid"), F.lit(q_blocks))), "queries")
    met = ["s", "cb", "qb"]
    cands = sliced(held.select("cid", "cb", "v")).withColumn("qb", numbers(q_blocks))

    def gather(at: tuple, c: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        ids, out = c["cid"].to_numpy(), []
        for i, p in _products(q, c) if len(c) and len(q) else ():
            best = np.argpartition(-p, min(depth, len(ids)) - 1, axis=1)[:, :depth]
            best = np.take_along_axis(best, np.argsort(-np.take_along_axis(p, best, axis=1), axis=1, kind="stable"), axis=1)
            out += [(qid, at[1], at[0], len(ids), x.min(), ids[b], x[b]) for qid, x, b in zip(q["qid"][i : i + len(p)], p, best)]
        return pd.DataFrame(out, columns=["qid", "cb", "s", "n", "least", "ids", "part"])

    listed = stored(cands.groupBy(*met).cogroup(sliced(q_rows).withColumn("cb", numbers(blocks)).groupBy(*met)).applyInPandas(gather, LISTS), "lists")
    least = listed.groupBy("qid", "s").agg(F.min("least").alias("least")).groupBy("qid").agg(F.transform(F.array_sort(F.collect_list(F.struct("s", "least"))), lambda x: x["least"]).alias("floor"))

    def by_block(lists: DataFrame) -> DataFrame:
        """One row of a query and block: the list of each node, ``depth`` entries or a block's at most."""
        nodes = F.array_sort(F.collect_list(F.struct("s", "ids", "part")))
        return lists.groupBy("qid", "cb").agg(nodes.alias("nodes"), F.max("n").alias("n")).select("qid", "cb", "n", F.transform("nodes", lambda x: x["ids"]).alias("ids"), F.transform("nodes", lambda x: x["part"]).alias("part"))

    def lows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for qid, ids, part, floor in zip(b["qid"], b["ids"], b["part"], b["floor"]):
                _, got, value = _known(ids, part)
                low = np.where(got, value, np.asarray(floor)[:, None]).sum(axis=0)
                out += [(qid, x) for x in np.sort(low)[::-1][:want]]
            yield pd.DataFrame(out, columns=["qid", "low"])

    low = by_block(listed).join(least, "qid").mapInPandas(lows, "qid long, low long")
    kth = low.withColumn("rn", F.row_number().over(W.partitionBy("qid").orderBy(F.desc("low")))).where(F.col("rn") == want).select("qid", F.col("low").alias("bar"))
    total = F.aggregate("floor", F.lit(0).cast("long"), F.try_add)
    summed = least.join(kth, "qid", "left").withColumn("total", total).withColumn("share", F.expr(f"coalesce(try_subtract(bar, total) div {slices}, 0L)"))
    cuts = stored(summed.select("qid", F.coalesce("bar", "total", F.lit(-(2**63))).alias("bar"), F.transform("floor", lambda x: F.coalesce(F.try_add(x, F.col("share")), x)).alias("cut")), "cutoffs")

    graded = listed.join(cuts.select("qid", "cut"), "qid").withColumn("least", F.expr("cut[s]")).drop("cut")
    short = (F.size("ids") < F.col("n")) & (F.element_at("part", -1) >= F.col("least"))
    back = stored(graded.where(short).select("qid", "cb", "s", "least"), "short")

    def collect(at: tuple, c: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        ids, out = c["cid"].to_numpy(), []
        for i, p in _products(q, c) if len(c) and len(q) else ():
            for qid, cut, x in zip(q["qid"][i : i + len(p)], q["least"][i : i + len(p)], p):
                over = np.flatnonzero(x >= cut)
                out.append((qid, at[1], at[0], len(ids), cut, ids[over], x[over]))
        return pd.DataFrame(out, columns=["qid", "cb", "s", "n", "least", "ids", "part"])

    deep = back.join(sliced(q_rows), ["qid", "s"])
    deep = cands.join(deep.select(*met).distinct(), met, "left_semi").groupBy(*met).cogroup(deep.groupBy(*met)).applyInPandas(collect, LISTS)
    enough = by_block(graded.where(~short).select("qid", "cb", "s", "n", "least", "ids", "part").unionByName(deep))

    def reach(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for qid, cb, n, ids, part, cut, bar in zip(b["qid"], b["cb"], b["n"], b["ids"], b["part"], b["cut"], b["bar"]):
                every, got, value = _known(ids, part)
                cut = np.asarray(cut)
                beyond = np.array([min(p.min(), t) if len(p) else t for p, t in zip(part, cut)])  # no unlisted part is more
                high = np.where(got, value, beyond[:, None]).sum(axis=0)
                some = (got & (value >= cut[:, None])).any(axis=0) & (high >= bar)
                if some.any():
                    out.append((qid, cb, every[some]))
            yield pd.DataFrame(out, columns=["qid", "cb", "cids"])

    open_ = stored(enough.join(cuts, "qid").mapInPandas(reach, "qid long, cb long, cids array<long>"), "open")

    def resolve(c: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(c) and len(q):
            c = c.sort_values("cid")
            width = max([1, *map(len, q["v"]), *map(len, c["v"])])
            ids, a, b = c["cid"].to_numpy(), _matrix(q["v"], width), _matrix(c["v"], width)
            for qid, x, cids in zip(q["qid"], a, q["cids"]):
                cids = np.asarray(cids)
                score = b[np.searchsorted(ids, cids)] @ x
                out += [(qid, cids[i], score[i]) for i in np.lexsort((cids, -score))[:want]]
        return pd.DataFrame(out, columns=["qid", "cid", "score"])

    left = open_.join(q_rows, "qid")
    whole = held.select("cid", "cb", "v").withColumn("qb", numbers(q_blocks))
    exact = whole.groupBy("cb", "qb").cogroup(left.groupBy("cb", "qb")).applyInPandas(resolve, "qid long, cid long, score long")
    exact = exact.withColumn("rn", F.row_number().over(W.partitionBy("qid").orderBy(F.desc("score"), "cid"))).where(F.col("rn") <= want).drop("rn")
    hits = asked.select("query_id", "qid").join(exact, "qid").join(classes.select("cid", "ids"), "cid").select("query_id", "score", F.explode("ids").alias("vec_id")).where(F.col("vec_id") != F.col("query_id"))
    return hits.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
