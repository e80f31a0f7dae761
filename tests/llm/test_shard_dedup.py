import hashlib
import zlib

import numpy as np
import pytest

from tierbit.llm import exactdedup, shard
from tierbit.llm.common import drop_rows, flagged

SCHEMA = "doc_id long, text string, lang string, shard string, SLOT int"
ROWS = [(i, f"text {i % 7}", None, "x", 1) for i in range(200)] + [(None, None, None, None, None), (5, "text 5", "en", None, 2), (5, "text 5", "en", None, 2), (900, "", "en", "y", 3), (901, "a" * 300_000, "de", "y", 3), (902, "  ", "de", "y", 3)]


def test_fisher_yates_is_a_permutation_and_uniform():
    rng = np.random.Generator(np.random.PCG64(1))
    seen = np.zeros((4, 4))
    for _ in range(4000):
        p = shard.fisher_yates(4, rng)
        assert sorted(p) == [0, 1, 2, 3]
        seen[np.arange(4), p] += 1
    assert abs(seen - 1000).max() < 150


@pytest.mark.parametrize("bucket_bytes", [3000, 1 << 20])
def test_shards_are_even_gapless_and_whole(spark, bucket_bytes, tmp_path):
    rows_in = ROWS + [(7, "one row", "en", None, 4)] * 400  # most of the table is one row
    spark.createDataFrame(rows_in, SCHEMA).coalesce(1).write.parquet(f"{tmp_path}/docs")
    docs = spark.read.parquet(f"{tmp_path}/docs")
    out = shard.shuffle_into_shards(docs, 8, bucket_bytes=bucket_bytes)
    rows = out.collect()
    sizes = [[r["slot"] for r in rows if r["shard"] == s] for s in range(8)]
    assert max(map(len, sizes)) - min(map(len, sizes)) <= 1 and sum(map(len, sizes)) == len(rows_in)
    assert all(sorted(s) == list(range(len(s))) for s in sizes)
    hot = [sum(r["doc_id"] == 7 and r["text"] == "one row" for r in rows if r["shard"] == s) for s in range(8)]
    assert min(hot) > 20
    key = lambda r: (str(r[0]), str(r[1]))
    assert sorted(map(key, [(r["doc_id"], r["text"]) for r in rows])) == sorted(map(key, rows_in))
    place = lambda df: sorted((str(r["doc_id"]), str(r["text"])[:9], r["shard"], r["slot"]) for r in df.collect())
    spark.conf.set("spark.sql.files.maxPartitionBytes", "4k")
    try:
        assert place(shard.shuffle_into_shards(docs, 8, bucket_bytes=bucket_bytes)) == place(out)
    finally:
        spark.conf.unset("spark.sql.files.maxPartitionBytes")
    other = shard.shuffle_into_shards(docs, 8, seed=3, bucket_bytes=bucket_bytes)
    assert place(other) != place(out)
    unread = shard.shuffle_into_shards(spark.createDataFrame(ROWS, SCHEMA), 3, bucket_bytes=bucket_bytes)
    assert unread.count() == len(ROWS) and sorted(unread.columns) == ["doc_id", "lang", "shard", "slot", "text"]


def test_registered_sharding_and_dedup(spark):
    import __spark_entry__ as E

    docs = {r["doc_id"]: r["text"] or "" for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()}
    got = E.queries()["op1_sharding"](spark, "/root/testdata/sf0.001").collect()
    assert {r["doc_id"]: (r["size"], r["text_crc32"]) for r in got} == {i: (len(t.encode()) + 1, zlib.crc32(t.encode())) for i, t in docs.items()} and len(got) == len(docs)
    by: dict = {}
    for r in got:
        assert r["law"] == "rows" and r["grown_shard"] is None
        by.setdefault(r["shard"], []).append(r["slot"])
    assert sorted(by) == list(range(8)) and all(sorted(s) == list(range(len(s))) for s in by.values())
    got = E.queries()["op9_exactdedup"](spark, "/root/testdata/sf0.001").collect()
    best: dict = {}
    for i, t in docs.items():
        best[t] = max(i, best.get(t, -1))
    assert {r["doc_id"]: r["keep_id"] for r in got} == {i: best[t] for i, t in docs.items()}


def test_empty_table(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert shard.shuffle_into_shards(empty, 8).count() == 0
    assert exactdedup.exact_dedup(empty).count() == 0


@pytest.mark.parametrize("keep,fan_in", [("largest", 2), ("smallest", 16)])
def test_exact_dedup_against_brute_force(spark, keep, fan_in):
    docs = spark.createDataFrame([*ROWS, *ROWS[:30]], SCHEMA).repartition(9)  # whole rows repeat
    groups: dict[str, list] = {}
    for r in [*ROWS, *ROWS[:30]]:
        groups.setdefault(r[1] or "", []).append(r[0])
    pick = {t: (max if keep == "largest" else min)((i for i in g if i is not None), default=None) for t, g in groups.items()}
    want = sorted((str(r[0]), str(pick[r[1] or ""]), len(groups[r[1] or ""]), hashlib.sha256((r[1] or "").encode()).hexdigest()) for r in [*ROWS, *ROWS[:30]])
    for hot in (10_000, 5):
        got = exactdedup.exact_dedup(docs, keep, fan_in, hot=hot).collect()
        assert sorted((str(r["doc_id"]), str(r["keep_id"]), r["group_size"], r["text_sha256"]) for r in got) == want
        kept = [r for r in got if r["kept"]]  # one row of each text, also where rows repeat
        assert all(r["doc_id"] == r["keep_id"] for r in kept)
        assert sorted(r["text_sha256"] for r in kept) == sorted(hashlib.sha256(t.encode()).hexdigest() for t in groups)


def test_runs_are_sorted_and_merging_keeps_them_so(spark):
    rows = exactdedup.digests(spark.range(5000).selectExpr("id as doc_id", "cast(id % 1500 as string) as text").repartition(7))
    rows = exactdedup.stored(rows, "digests")
    runs = exactdedup.sorted_runs(rows, True, 64, 800).collect()
    assert len({r["run"] for r in runs}) == 7 and max(r["n"] for r in runs) < 400
    for r in runs:
        e = np.frombuffer(r["entries"], exactdedup.ENTRY)
        assert (np.diff(e["d0"].astype(object)) > 0).all() and len(set((e["d0"] >> np.uint64(60)).tolist())) == 1
    for fan_in in (2, 3, 16):
        got = exactdedup.merge_runs(rows, "largest", fan_in, segment=64)
        assert got.count() == 1500 and got.agg({"group_size": "sum"}).first()[0] == 5000
        assert {r[0] for r in got.select("keep_id").collect()} == set(range(3500, 5000))


def test_digest_is_not_trusted_alone(spark):
    same = spark.createDataFrame([(bytearray(32), 3, 1, 1, 1), (bytearray(32), 3, 2, 2, 2), (bytearray(32), 4, 2, 3, 3)], "text_sha256 binary, n_bytes long, check long, row long, doc_id long")
    assert exactdedup.merge_runs(same).count() == 3


def test_survivors_keep_one_row_of_each_text(spark):
    rows = [*ROWS, *ROWS[:30], (5, "text 5", "fr", None, 2), (None, None, "en", None, 1)]
    got = exactdedup.survivors(spark.createDataFrame(rows, SCHEMA).repartition(5))
    assert got.columns == ["doc_id", "text", "lang", "shard", "SLOT"]
    best = {}
    for r in rows:
        best[r[1] or ""] = max(-1 if r[0] is None else r[0], best.get(r[1] or "", -1))
    out = got.collect()
    assert sorted((r["text"] or "", -1 if r["doc_id"] is None else r["doc_id"]) for r in out) == sorted(best.items())
    assert exactdedup.survivors(spark.createDataFrame([], SCHEMA)).count() == 0


def test_extreme_and_null_ids(spark):
    low, high = -(2**63), 2**63 - 1
    docs = spark.createDataFrame([(low, "a"), (None, "a"), (high, "b"), (low, "b"), (None, "c"), (None, "c")], "doc_id long, text string")
    for keep, b in (("largest", high), ("smallest", low)):
        got = {r["text_sha256"][:4]: (r["keep_id"], r["group_size"]) for r in exactdedup.exact_dedup(docs, keep).collect() if r["kept"]}
        sha = lambda t: hashlib.sha256(t.encode()).hexdigest()[:4]
        assert got == {sha("a"): (low, 2), sha("b"): (b, 2), sha("c"): (None, 2)}


def test_bitmap_and_drop_rows(spark):
    rows = spark.range(2000).selectExpr("id as doc_id", "cast(id as string) as text", "id as _x")
    gone = rows.where("doc_id % 100 = 3").selectExpr("doc_id", "xxhash64(text) as tag")
    assert flagged(rows, gone, ["doc_id"], 64).where("not maybe").where("doc_id % 100 = 3").count() == 0
    assert [r[0] for r in drop_rows(rows, gone).where("doc_id % 100 = 3").collect()] == []
    assert drop_rows(rows, gone).count() == 1980 and drop_rows(rows, gone).columns == rows.columns
