import hashlib
import math
import os
import random
import re
import time

from pyspark.sql import functions as F

from tierbit.llm import pii

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
TEXTS = [
    "", None, "a@b.c_d@e.f x@y", "1.2.3.4.5 and 999.1.1.1 and 0001.2.3.4", "a@b@c.d .@x.y-", "4111 1111 1111 1111 and 4111-1111-1111-1112", "+1 (523) 555-1055, +12, +1 2 3 4 5 6 7 8 9 0 1 2 3 4 5 6", "🙂 me@x.org 🙂 10.0.0.1",
    "call (555) 123-4567 or john [at] example [dot] org", "12345678901234567890123 4242424242424242", "9" * 50_000, "." * 20_000 + "@" * 50, "1." * 30_000, "a" * 60_000 + "@b.co", "+1" + " " * 40_000, "4242 4242 4242 4242 1", "x+1 5551234567y",
]


def brute(text):
    def luhn(d):
        return sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(d))) % 10 == 0

    out = []
    for kind, p in PATTERNS.items():
        for m in re.finditer(p, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {"email": lambda: True, "ip": lambda: all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in m[0].split(".")), "card": lambda: 16 <= len(digits) <= 19 and luhn(digits), "phone": lambda: 8 <= len(digits) <= 15}[kind]()
            if ok:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


def test_base_spans_equal_the_plain_patterns(spark):
    docs = spark.createDataFrame([(i, t, "x") for i, t in enumerate(TEXTS)] + [(None, "q@w.e", None), (3, "q@w.e", None), (3, "q@w.e", None)], "doc_id long, text string, base string")
    out = pii.find_pii(docs).select("doc_id", pii.spelled(F.col("base")).alias("s")).collect()
    assert len(out) == len(TEXTS) + 3
    for r in out:
        if r["doc_id"] is not None and r["doc_id"] != 3:
            assert r["s"] == brute(TEXTS[r["doc_id"]]), r["doc_id"]
    assert sorted(r["s"] for r in out if r["doc_id"] == 3) == sorted([brute(TEXTS[3]), "email:0:5", "email:0:5"])
    assert pii.find_pii(docs.limit(0)).count() == 0


WIDE = {
    "good": "call (212) 555-0147 or mail john [at] example [dot] org, card 4242.4242.4242.4242, host 2001:db8:1:2:3:4:5:6 end",
    "bad": "row (012) 155-0147 of set 12 [at] 34 [dot] 56, part 4242.4242.4242.4241, time 1:2:3:4:5:6:7:8 end",
}


def test_added_spans_are_those_that_look_like_valid_ones(spark):
    """Contexts of wide forms are learned from their own checks; what is added are planted spans, what isn't is refused."""
    rng = random.Random(5)
    rows = [(i, f"{rng.choice(['one', 'two', 'three', 'four'])} {i} {WIDE['good' if i % 2 else 'bad']} {'and 4242 4242 4242 4242' if i % 3 else 'and 1234567890123456789'}") for i in range(600)]
    out = pii.find_pii(spark.createDataFrame(rows, "doc_id long, text string"), precision=0.9)
    texts = dict(rows)
    for r in out.collect():
        got = sorted((a["kind"], texts[r["doc_id"]][a["s"] : a["e"]]) for a in r["added"])
        assert got == ([(0, "john [at] example [dot] org"), (1, "2001:db8:1:2:3:4:5:6"), (2, "4242.4242.4242.4242"), (3, "(212) 555-0147")] if r["doc_id"] % 2 else []), r["doc_id"]
        assert all(a["wide"] == 1 and a["hit"] == texts[r["doc_id"]][a["s"] : a["e"]] for a in r["added"])
        assert [b["hit"] for b in r["base"]] == (["4242 4242 4242 4242"] if r["doc_id"] % 3 else [])


def test_threshold_takes_equal_scores_together():
    class Flat:
        def score(self, x):
            return float(x[0])

    cells = [((2,), 10.0, 0.0), ((1, 0), 9.0, 0.0), ((1, 1), 0.0, 9.0), ((0,), 0.0, 50.0)]
    assert pii.threshold(Flat(), cells, 0.9) == 2.0 and pii.threshold(Flat(), cells, 0.6) == 1.0
    assert pii.threshold(Flat(), [((3,), 0.0, 1.0)], 0.5) == math.inf


def test_very_many_matches_in_one_text(spark):
    """Work follows the number of matches; wide ones meet base ones by halving."""
    n = 100_000
    docs = spark.createDataFrame([(1, "a@b.co " * n), (2, "(212) 555-0147 10.0.0.1 " * (n // 2)), (3, "x")], "doc_id long, text string")
    start = time.perf_counter()
    found = pii.stored(pii.proposals(docs), "many")
    got = {r["doc_id"]: r for r in found.select("doc_id", F.size("base").alias("b"), F.size("wide").alias("w"), F.expr("try_element_at(base, -1).e").alias("e")).collect()}
    assert time.perf_counter() - start < 90
    assert (got[1]["b"], got[1]["w"], got[1]["e"]) == (n, 0, 7 * n - 1) and (got[2]["b"], got[2]["w"]) == (n // 2, n // 2) and got[3]["b"] == 0
    text = "🙂 a@b.co " * 20_000
    spans = found.limit(1).select(F.lit(text).alias("t")).select("t", F.transform(F.sequence(F.lit(0), F.lit(19_999)), lambda i: F.struct(F.lit(0).alias("kind"), (i * 9 + 2).alias("s"), (i * 9 + 8).alias("e"))).alias("x"))
    start = time.perf_counter()
    assert spans.select(pii.redact(F.col("t"), F.col("x"))).first()[0] == "🙂 [email] " * 20_000
    assert time.perf_counter() - start < 60


def test_wide_proposals_are_clear_of_valid_base_spans(spark):
    rows = [(1, "+1 (523) 555-1055 then (523) 555-1055"), (2, "+1 (826) 555-4081 190 190 190 190"), (3, "4242 4242 4242 4242.4242.4242.4242")]
    got = {r["doc_id"]: [w["s"] for w in r["wide"]] for r in pii.proposals(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: [23], 2: [3], 3: []}


def test_redaction(spark):
    rows = [("x 10.0.0.1 y", [(1, 2, 10)], "x [ip] y"), ("🙂a@b.c🙂", [(0, 1, 6)], "🙂[email]🙂"), ("abcdefgh", [(2, 1, 5), (0, 3, 7), (1, 0, 2)], "[ip]h"), ("ab", [], "ab"), ("", [], ""), (None, [(0, 0, 1)], None), ("ab", [(0, 0, 1), (1, 1, 2)], "[email][ip]")]
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "i int, t string, x array<struct<kind:int,s:int,e:int>>, want string")
    for r in df.select("want", pii.redact(F.col("t"), F.col("x")).alias("got")).collect():
        assert r["got"] == r["want"]


def test_trees_learn_an_interaction():
    cells = [((a, b), 50.0 * (a == b), 50.0 * (a != b)) for a in range(2) for b in range(2)]
    cells[0] = ((0, 0), 60.0, 0.0)
    t = pii.Trees(["a", "b"]).fit(cells)
    assert t.score((1, 1)) > 1 > -1 > t.score((0, 1))
    assert pii.threshold(t, cells, 0.95) > t.score((0, 1))


def test_no_python_in_the_plan(spark, capsys):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    pii.proposals(docs).explain("formatted")
    assert not re.search("Python|Pandas|Arrow", capsys.readouterr().out)


def test_pipeline_stages(spark):
    import corpus_pipeline as C

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet").withColumn("bucket", F.lit(1))
    extra = [(None, None, None, None, None, 1), (5000, "", "en", "s", 0, 1), (5001, "12 34", "en", "s", 5, 1), (5001, "12 34", "en", "s", 5, 1)]
    docs = docs.unionByName(spark.createDataFrame(extra, docs.schema))
    all_rows = {(r["doc_id"], r["text"]) for r in docs.collect()}
    a = C.language(spark, docs, sf)
    lang = {(r["doc_id"], r["text"]) for r in a.collect()}
    assert a.columns == docs.columns and lang == {x for x in all_rows if x[1] and any(map(str.isalpha, x[1]))}
    b = C.exact(spark, a, sf)
    best = {}
    for i, t in lang:
        best[t] = max(i, best.get(t, -1))
    assert {(r["doc_id"], r["text"]) for r in b.collect()} == {(i, t) for t, i in best.items()} and b.columns == docs.columns
    c = C.near(spark, b, sf)
    from tests.llm.test_neardup import brute as groups

    want = groups([(r["doc_id"], r["text"]) for r in b.collect()])
    least = {}
    for i, root in want.items():
        least[root] = min(i, least.get(root, i))
    assert {r["doc_id"] for r in c.collect()} == set(least.values())
    d = C.mix(spark, c, sf)
    n = {r["doc_id"] for r in d.collect()}
    assert d.columns == docs.columns and n <= set(least.values()) and len(n) > 0.5 * len(least)
    e = C.pack(spark, d, sf)
    assert {r["doc_id"] for r in e.select("doc_id").distinct().collect()} == n
    empty = docs.limit(0)
    for _, stage in C.STAGES:
        assert stage(spark, empty, sf).count() == 0


CONTRACT = {
    "op1": "doc_id bigint, size bigint, text_crc32 bigint, law string, shard int, slot bigint, grown_shard int",
    "op2": "query_id bigint, rank int, vec_id bigint, score bigint",
    "op3": "doc_id bigint, held_out boolean, lang_pred string, score double",
    "op4": "doc_id bigint, cluster_id bigint, links bigint",
    "op5": "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string",
    "op6": "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint",
    "op7": "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint",
    "op8": "doc_id bigint, prob double, copies bigint",
    "op9": "doc_id bigint, keep_id bigint, group_size bigint, kept boolean, text_sha256 string",
    "op10": "doc_id bigint, held_out boolean, score double, predicted int",
}


def test_every_contract_query_has_its_columns(spark):
    """As registered, with intermediate tables in the folder that the session names."""
    import __spark_entry__ as E

    queries = {n.split("_")[0]: q for n, q in E.queries().items() if re.match(r"op[0-9]+_", n)}
    assert sorted(queries) == sorted(CONTRACT)
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()}
    base = spark.conf.get("spark.checkpoint.dir")
    before = set(os.listdir(base.removeprefix("file://")))
    for op, columns in CONTRACT.items():
        got = queries[op](spark, "/root/testdata/sf0.001")
        types = dict(got.dtypes)
        assert {c.split()[0]: types.get(c.split()[0]) for c in columns.split(", ")} == dict(c.split() for c in columns.split(", ")), op
        rows = got.collect()
        if op not in ("op2", "op7"):
            assert sorted(r["doc_id"] for r in rows) == sorted(texts), op
        if op == "op5":
            for r in rows:
                assert r["base_sha256"] == hashlib.sha256(brute(texts[r["doc_id"]]).encode()).hexdigest()
                assert not r["spans"] or all(re.fullmatch("(email|ip|card|phone):[0-9]+:[0-9]+", x) for x in r["spans"].split(","))
    assert len(set(os.listdir(base.removeprefix("file://"))) - before) > 10


def test_language_rule_holds_where_nothing_is_learned(spark):
    import corpus_pipeline

    rows = [(1, None, None, "s"), (2, "123 !", None, "s"), (3, "12 ä", None, "s"), (4, "", None, "s")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    assert [r["doc_id"] for r in corpus_pipeline.language(spark, docs, "").collect()] == [3]
