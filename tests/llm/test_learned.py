import numpy as np
import pytest
from pyspark.sql import functions as F

from tierbit.llm import langid, mixing, toxicity
from tierbit.llm.common import id_crc

SF = "/root/testdata/sf0.01"
SCHEMA = "doc_id long, text string, lang string, source string, lang_pred string, score string"


def test_language_on_held_out_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    held = F.coalesce(id_crc() % 3 == 1, F.lit(False))
    out = langid.identify(docs, langid.fit(docs, ~held)).where(held)
    right, n = out.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int")), F.count("*")).first()
    assert n > 300 and right > 0.97
    low, high = out.agg(F.min("score"), F.max("score")).first()
    assert 0 <= low <= high <= 1


def test_language_edges(spark):
    rows = [(i, "the cat and the dog", "en", "s", "x", "y") for i in range(6)] + [(9, "der hund und die katze", "de", "s", "x", "y")] * 3 + [(None, None, None, None, None, None), (20, "123 456 !!", None, None, None, None), (21, "ä" * 30, None, None, None, None)]
    docs = spark.createDataFrame(rows, SCHEMA)
    model = langid.fit(docs, F.lit(True))
    out = langid.identify(docs, model).collect()
    assert len(out) == len(rows) and all((r["lang_pred"] == "und") == (r["doc_id"] in (None, 20)) for r in out)
    assert langid.identify(docs.limit(0), model).count() == 0
    nothing = langid.fit(docs.where("lang is null"), F.lit(True))
    assert {r["lang_pred"] for r in langid.identify(docs, nothing).collect()} == {"und"}


def test_long_texts_are_read_whole():
    assert np.abs(langid.grams("ab cd " * 400_000).sum() / 3 - 2_400_000) < 10_000


def test_follow_the_leader_is_sparse():
    rng = np.random.default_rng(0)
    rows = [(np.sort(rng.choice(200, 20, False)), np.ones(20) / 4.5, int(i % 2)) for i in range(200)]
    rows = [(np.append(at, 200 + y), np.append(x, 1.0), y) for at, x, y in rows]
    w, _ = langid.follow_the_leader(rows, 202, 2, l1=1.0)
    assert (w[:200] == 0).mean() > 0.5 and w[200, 0] > 0 and w[201, 1] > 0


def test_temperature_calibrates():
    rng = np.random.default_rng(1)
    z = rng.normal(size=(4000, 3))
    y = np.array([rng.choice(3, p=langid.softmax(r)) for r in z])
    assert abs(langid.calibrate(z * 4, y) - 4) < 0.5


def test_toxicity_on_held_out_documents(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    held = F.coalesce(id_crc() % 4 == 2, F.lit(False))
    out = toxicity.score(docs, toxicity.fit(docs, labels, ~held)).where(held).join(labels, "doc_id").select("score", "toxic").collect()
    pos, neg = (np.array([r["score"] for r in out if r["toxic"] == y]) for y in (1, 0))
    assert (pos[:, None] > neg[None, :]).mean() > 0.9
    assert (neg >= 0.3).mean() < 0.03


def test_label_model_discounts_echoes():
    rng = np.random.default_rng(2)
    y = rng.random(4000) < 0.3
    noise = rng.random(4000) < 0.3
    votes = [np.where(rng.random(4000) < 0.2, ~y, y), np.where(rng.random(4000) < 0.2, ~y, y), *[noise] * 3]
    masks = sum(v.astype(np.int64) << i for i, v in enumerate(votes))
    pattern, n = np.unique(masks, return_counts=True)
    model = toxicity.LabelModel(5).fit(pattern, n, masks[:200], y[:200].astype(int))
    assert any(set(g) == {2, 3, 4} for g in model.groups)
    q = model.posterior(masks)
    assert ((q > 0.5) == y).mean() > 0.75


def test_toxicity_edges(spark):
    docs = spark.createDataFrame([(1, None, None, None, None, None), (None, "x", None, None, None, None), (2, "a" * 200_000, None, None, None, None), (2, "b", None, None, None, None)], SCHEMA)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r["score"] for r in toxicity.score(docs, toxicity.fit(docs, none, F.lit(True))).collect()} == {0.0}
    some = spark.createDataFrame([(1, 0, 1), (2, 0, 0), (2, 1, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    got = toxicity.score(docs, toxicity.fit(docs, some, F.lit(True))).collect()
    assert len(got) == 4 and all(0 <= r["score"] <= 1 for r in got)
    assert toxicity.score(docs.limit(0), None).count() == 0


def test_raking_meets_all_marginals():
    rng = np.random.default_rng(3)
    cells = [(f"s{a}", f"l{b}", f"t{c}", float(rng.integers(1, 1000))) for a in range(5) for b in range(3) for c in range(4)]
    mix = mixing.Mix(targets={"lang": {"l0": 1.0, "l1": 1.0, "l2": 2.0}}, rounds=60)
    w, goals = mixing.rake(cells, mix), mixing._targets(cells, mix)
    for i in range(3):
        for k, g in goals[i].items():
            assert abs(sum(x for c, x in zip(cells, w) if c[i] == k) - g) < 1e-6
    tokens, factors = [c[3] for c in cells], [x * sum(c[3] for c in cells) / c[3] for c, x in zip(cells, w)]
    c = mixing.calibrate(tokens, factors, mixing.Mix(budget=0.5))
    assert abs(sum(t * min(1, c * f) for t, f in zip(tokens, factors)) / sum(tokens) - 0.5) < 1e-6


def test_large_cell_tables_rake_the_same(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    key = lambda df: sorted((r["doc_id"], round(r["factor"], 6), r["prob"]) for r in df.collect())
    small = mixing.mixed(docs, mixing.Mix(rounds=4))
    large = mixing.mixed(docs, mixing.Mix(rounds=4, max_cells=1))
    assert [x[:2] for x in key(small)] == [x[:2] for x in key(large)]
    assert max(abs(a[2] - b[2]) for a, b in zip(key(small), key(large))) < 1e-9


def test_mixing_with_columns_named_like_its_results(spark):
    docs = spark.createDataFrame([(i, "some text " * i, "en", f"s{i % 2}", "t", 5, 0.5, None, 9, "r") for i in range(40)], "doc_id long, text string, lang string, source string, topic string, tokens int, factor double, prob string, copies int, `row` string")
    got = mixing.mixed(docs, carry=True).where("copies > 0").select("row.*")
    plain = mixing.mixed(docs.select("doc_id", "text", "lang", "source")).where("copies > 0")
    assert got.columns == docs.columns and sorted(r[0] for r in got.collect()) == sorted(r[0] for r in plain.collect())


def test_a_repeated_id_teaches_the_same_text_every_time(spark):
    rng = np.random.default_rng(9)
    rows = [(i // 2, f"{'vile' if i // 2 % 2 else 'fine'} words {rng.integers(1 << 30)}") for i in range(400)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, toxic int")
    made = [toxicity.fit(spark.createDataFrame(r, "doc_id long, text string").repartition(n), labels, F.lit(True)) for r, n in ((rows, 3), (rows[::-1], 5))]
    assert np.array_equal(made[0].weights, made[1].weights) and (made[0].a, made[0].b) == (made[1].a, made[1].b)


@pytest.mark.parametrize("repeats", [False, True])
def test_mixing_edges(spark, repeats):
    rows = [(None, None, None, None, None, None), (1, "x", "en", "s", None, None), (1, "x", "en", "s", None, None), (2, "y" * 90_000, "de", "s", None, None)]
    docs = spark.createDataFrame(rows, SCHEMA)
    assert mixing.mixed(docs, mixing.Mix(repeats=repeats)).count() == 4
    assert mixing.mixed(docs.limit(0)).count() == 0


def test_hot_copies_do_not_thin_a_language(spark):
    """A language with most of its rows in copies of one text is learned from its other texts."""
    rng = np.random.default_rng(6)
    text = lambda letters: " ".join("".join(rng.choice(list(letters), 5)) for _ in range(12))
    rows = [(text("abcdefgh"), "aa") for _ in range(300)] + [(text("stuvwxyz"), "zz") for _ in range(300)]
    copies = spark.range(60_000).selectExpr("'hhhh' as text", "'aa' as lang")
    model = langid.fit(spark.createDataFrame(rows, "text string, lang string").unionByName(copies), F.lit(True), per_class=100)
    assert sum(model.predict(text("abcdefgh"))[0] == "aa" for _ in range(60)) >= 58
