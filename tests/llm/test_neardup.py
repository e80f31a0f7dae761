import numpy as np
import pytest

from tierbit.llm import neardup as N

SCHEMA = "doc_id long, text string, source string, class string"


def words(rng, n):
    return [f"w{x}" for x in rng.integers(0, 5000, n)]


def corpus(seed=1):
    rng = np.random.default_rng(seed)
    texts = []
    for g in range(25):
        base = words(rng, int(rng.integers(40, 200)))
        texts.append(" ".join(base))
        for _ in range(int(rng.integers(0, 5))):
            t = list(base)
            for _ in range(int(rng.integers(1, 4))):
                t[int(rng.integers(len(t)))] = "changed"
            texts.append(" ".join(t))
    shared = words(rng, 60)
    texts += [" ".join(words(rng, 150) + shared + words(rng, 150)) for _ in range(20)]  # a common passage, not copies
    hot = words(rng, 120)
    for i in range(60):  # one large group of near copies
        t = list(hot)
        t[i * 2] = f"x{i}"
        texts.append(" ".join(t))
    texts += ["Short  Text", "short text", "other text", "", None, "   "]
    return [(i, t, "s", None) for i, t in enumerate(texts)]


def shingle_set(t):
    w = (t or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else frozenset()


def brute(rows):
    sets, parent = {i: shingle_set(t) for i, t, *_ in rows}, {r[0]: r[0] for r in rows}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i in ids:
        for j in ids:
            if j < i and ((not sets[i] and not sets[j]) or (sets[i] and sets[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]))):
                a, b = sorted((find(i), find(j)))
                parent[b] = a
    return {i: find(i) for i in ids}


def test_groups_equal_brute_force(spark):
    rows = corpus()
    got = N.near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()
    want = brute(rows)
    root = {}
    for i, r in want.items():
        root.setdefault(r, []).append(i)
    assert {r["doc_id"]: r["cluster_id"] for r in got} == {i: min(g) for g in root.values() for i in g}
    assert sum(r["kept"] for r in got) == len(root)
    assert all(r["cluster_size"] == len(root[want[r["doc_id"]]]) for r in got)


def test_edits_of_one_original_meet_it(spark):
    """Edits that are near copies of the original alone, not of each other, still join its group."""
    rng = np.random.default_rng(8)
    base = words(rng, 300)
    texts = []
    for i in range(400):
        t, at = list(base), int(rng.integers(0, 280))
        t[at : at + 20] = words(rng, 20)
        t[(at + 150) % 300] = "changed"
        texts.append(" ".join(t))
    rows = [(i, t, "s", None) for i, t in enumerate([*texts[:200], " ".join(base), *texts[200:]])]
    want = brute(rows)
    got = {r["doc_id"]: r["cluster_id"] for r in N.near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == want and set(got.values()) == {0}


def test_signatures_estimate_weighted_similarity():
    rng = np.random.default_rng(0)
    errors = []
    for _ in range(120):
        n = int(rng.integers(3, 300))
        a = rng.integers(0, 1 << 62, n).astype(np.uint64)
        b = a.copy()
        m = int(n * rng.random())
        b[:m] = rng.integers(0, 1 << 62, m)
        w, v = 1 + 3 * rng.random(n), 1 + 3 * rng.random(n)
        v[:m] = w[:m]
        low = np.minimum(w[m:], v[m:]).sum()
        j = low / (w.sum() + v.sum() - low)
        x, y = N.dart_signatures([(a, w), (b, v)], 256)
        errors.append((x == y).mean() - j)
    assert abs(np.mean(errors)) < 0.01 and np.std(errors) < 0.05


def test_signature_does_not_depend_on_batch_or_order():
    rng = np.random.default_rng(2)
    sets = [(rng.integers(0, 1 << 62, n).astype(np.uint64), 1 + rng.random(n)) for n in (1, 4, 50, 900)]
    alone = [N.dart_signature(*s, 120) for s in sets]
    assert np.array_equal(N.dart_signatures(sets, 120), np.stack(alone))
    order = rng.permutation(50)
    assert np.array_equal(alone[2], N.dart_signature(sets[2][0][order], sets[2][1][order], 120))
    assert not N.dart_signature(np.zeros(0, np.uint64), np.zeros(0), 120).any()


def test_candidates_stay_linear_in_a_large_bucket(spark):
    entries = spark.range(3000).selectExpr("1L as band", "cast(lpad(cast(id as string), 6, '0') as binary) as class")
    assert N.candidates(entries, share=100).count() <= 6000
    assert N.candidates(entries, share=100, near=4).count() <= 5 * 3000


def test_components_of_a_long_chain(spark):
    key = lambda i: bytearray(f"{i:05d}".encode())
    links = spark.createDataFrame([(key(i), key(i + 1)) for i in range(120) if i % 40 != 39], "a binary, b binary")
    roots = {bytes(r["class"]): bytes(r["root"]) for r in N.components(links).collect()}
    assert {r for r in roots.values()} == {b"00000", b"00040", b"00080"} and roots[b"00039"] == b"00000"


@pytest.mark.parametrize("rows", [[], [(None, None, None, None)], [(None, "a b c", None, None), (3, "A  b c", None, None), (3, "A  b c", None, None)]])
def test_edges(spark, rows):
    got = N.near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()
    assert len(got) == len(rows)
    if len(rows) == 3:
        assert {r["cluster_id"] for r in got} == {-1} and sum(r["kept"] for r in got) == 1


def test_families_of_one_template_are_tried_against_each_other(spark):
    """Several families share buckets: the groups are still those of all pairs."""
    rng = np.random.default_rng(21)
    base = words(rng, 400)
    texts = []
    for f in range(12):
        own = list(base)
        for at in rng.choice(80, 9, replace=False):
            own[at * 5] = f"f{f}x{at}"
        for _ in range(25):
            t = list(own)
            for at in rng.choice(400, 5, replace=False):
                t[at] = f"e{int(rng.integers(1 << 40))}"
            texts.append(" ".join(t))
    rows = [(i, t, "s", None) for i, t in enumerate(texts)]
    want = brute(rows)
    docs = spark.createDataFrame(rows, SCHEMA)
    for block in (256, 7):
        got = {r["doc_id"]: r["cluster_id"] for r in N.near_duplicates(docs, block=block).collect()}
        assert got == want


def test_remainder_compares_every_pair_across_roots(spark):
    """In blocks: each pair of different roots in a common bucket is met once, whatever the blocks' size."""
    rng = np.random.default_rng(4)
    key = lambda i: f"{i:04d}".encode()
    size, sigs = 20, {}
    base = rng.integers(0, 256, (5, size))
    for i in range(120):
        s = base[i % 5].copy()
        s[rng.integers(0, size, int(rng.integers(0, 6)))] = 7
        sigs[i] = s.astype(np.uint8)
    keys = {i: [int(k) * 1000 + int(s[4 * k : 4 * k + 4].astype(int).sum()) for k in range(5)] for i, s in sigs.items()}
    mass = {i: float(rng.integers(80, 120)) for i in sigs}
    root = {i: i % 7 for i in sigs if i % 3}
    entries = spark.createDataFrame([(bytearray(key(i)), b, mass[i]) for i in sigs for b in keys[i]], "class binary, band long, mass double")
    roots = spark.createDataFrame([(bytearray(key(i)), bytearray(key(1000 + r))) for i, r in root.items()], "class binary, root binary")
    table = spark.createDataFrame([(bytearray(key(i)), bytearray(s.tobytes()), keys[i]) for i, s in sigs.items()], "class binary, sig binary, bands array<long>")
    own = lambda i: 1000 + root[i] if i in root else i
    want = {(i, j) for i in sigs for j in sigs if i < j and set(keys[i]) & set(keys[j]) and own(i) != own(j) and min(mass[i], mass[j]) >= 0.8 * max(mass[i], mass[j]) and (sigs[i] == sigs[j]).mean() >= N.agreement(0.8, size)}
    assert len(want) > 100
    for block in (256, 9):
        groups: dict = {}
        for r in N.remainder(entries, roots, table, size, 0.8, block).collect():
            groups.setdefault((r["band"], r["i"], r["j"]), []).append((r["band"], r["i"], r["j"], bytes(r["class"]), bytes(r["root"]), r["mass"], r["block"], bytes(r["sig"]), r["bands"]))
        got = [tuple(sorted((int(rows[x][3]), int(rows[y][3])))) for rows in groups.values() for x, y in N.close_pairs(rows, size, 0.8)]
        assert len(got) == len(set(got)) and set(got) == want
        assert max(map(len, groups.values())) <= 4 * block


def test_recall_against_all_pairs_of_the_given_table(spark):
    """Every pair of different normalised texts at 0.8 or more ends in one group."""
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()]
    got = {r["doc_id"]: r["cluster_id"] for r in N.near_duplicates(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).collect()}
    by: dict = {}
    sets = {}
    for i, t in rows:
        norm = N.normalised(t)
        if norm not in by:
            sets[i] = set(N.shingles(norm)[0].tolist())
            by[norm] = i
        assert got[i] == got[by[norm]]
    where: dict = {}
    for i, s in sets.items():
        for x in s:
            where.setdefault(x, []).append(i)
    common: dict = {}
    for ids in where.values():
        for n, i in enumerate(ids):
            for j in ids[:n]:
                common[j, i] = common.get((j, i), 0) + 1
    pairs = [p for p, n in common.items() if n >= 0.8 * (len(sets[p[0]]) + len(sets[p[1]]) - n)]
    assert pairs and all(got[i] == got[j] for i, j in pairs)


def test_copies_that_repeat_their_passages(spark):
    """A text twice or more over has nearly the shingle set of the text once."""
    rng = np.random.default_rng(31)
    texts = []
    for g in range(20):
        base = words(rng, 120)
        texts += [" ".join(base * k) for k in (1, 2, 3, 5)]
    rows = [(i, t, "s", None) for i, t in enumerate(texts)]
    got = {r["doc_id"]: r["cluster_id"] for r in N.near_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == brute(rows) and len(set(got.values())) == 20


def test_weights_measure_tells_repeats_apart(spark):
    text = " ".join(words(np.random.default_rng(32), 120))
    docs = spark.createDataFrame([(0, text, "s", None), (1, f"{text} {text} {text}", "s", None), (2, f"{text} end", "s", None)], SCHEMA)
    got = {r["doc_id"]: r["cluster_id"] for r in N.near_duplicates(docs, measure="weights").collect()}
    assert got == {0: 0, 1: 1, 2: 0}
