"""Methods of the index, resumption, verification and baselines, one query each."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from tierbit.catalog import query
from tierbit.catalog import sqltext as S
from tierbit.config import PAPER, SMALL, IndexSpec
from tierbit.functions.bits import bits_on, rank_before
from tierbit.operators import baselines as B
from tierbit.operators import build, merkle, resume, search, sparse, verify
from tierbit.operators.search import All, Any
from tierbit.plans import measures, route
from tierbit.sources import ledger as L
from tierbit.sources import storage, store

E_COLS = ["event_id", "user_id", "event_type", "value", "props"]
R = 0x0123456789ABCDEF0123456789ABCDEF | 0x88888888888888888888888880000000
U7 = (("user_id", "7"),)
BUY = (("event_type", "purchase"),)


def pf(spark, sf, name, dims=None):
    own = {d: e for d, e in L.DIMS[name].items() if dims is None or d in dims}
    return L.extract(L.ledger(spark, sf, name), own)


def masks(spark, sf, name, spec=PAPER, dims=None, **kw):
    return build.keyed(pf(spark, sf, name, dims), spec, **kw)


MASK_COLS = ["level", "dim", "key", "tree", "node", "mask"]
M_OUT = "SELECT level, dim, key, tree, node, mask FROM m"

# positions, digests, features


@query(f"SELECT l_orderkey, l_linenumber, l_partkey, pos FROM {S.LINES}")
def a1_positions(spark, sf):
    return L.lines(spark, sf).select("l_orderkey", "l_linenumber", "l_partkey", "pos")


@query("SELECT event_id, event_id AS pos FROM events")
def a1_file_positions(spark, sf):
    return L.with_file_positions(L.table(spark, sf, "events")).select("event_id", "pos")


@query(f"SELECT event_id, {S.digest(E_COLS)} AS digest FROM events")
def a2_digest(spark, sf):
    return L.with_digest(L.table(spark, sf, "events"), E_COLS).select("event_id", "digest")


@query(f"SELECT pos, user_id, digest FROM (SELECT event_id AS pos, user_id, {S.digest(E_COLS)} AS digest FROM events)")
def a3_split_roles(spark, sf):
    provider, chain = L.split_roles(L.events(spark, sf), E_COLS)
    return provider.join(chain, "pos").select("pos", "user_id", "digest")


for _n in ("E", "O", "L"):
    query(f"WITH {S.features(_n)} SELECT pos, dim, key FROM pf", name=f"a4_features_{_n.lower()}")(lambda spark, sf, n=_n: pf(spark, sf, n))

TOKENS = "SELECT doc_id AS pos, t AS key FROM (SELECT doc_id, unnest(list_distinct(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+'))) AS t FROM documents) WHERE t <> ''"


@query(f"SELECT pos, count(*) AS tokens, min(key) AS first_token FROM ({TOKENS}) GROUP BY pos")
def a5_keyword_sets(spark, sf):
    docs = L.table(spark, sf, "documents").withColumn("pos", F.col("doc_id"))
    return L.extract_multi(docs, "text").groupBy("pos").agg(F.count("*").alias("tokens"), F.min("key").alias("first_token"))


@query("SELECT event_id AS pos, 'defined' AS dim, 'value>=88' AS key FROM events WHERE value >= 88.0")
def a6_predicate_features(spark, sf):
    return L.define(L.events(spark, sf), L.DEFINED["E"])


@query(f"WITH {S.features('L14', ['value', 'to'])}, c AS (SELECT dim, key, count(*) AS n FROM pf GROUP BY ALL) SELECT dim, count(*) AS features FROM c WHERE n >= CASE WHEN dim = 'value' THEN 2 ELSE 1 END GROUP BY dim")
def a7_min_support(spark, sf):
    return L.supported(pf(spark, sf, "L14", ["value", "to"]), {"value": 2}).groupBy("dim").agg(F.count_distinct("key").alias("features"))


@query(f"WITH {S.features('E', ['user_id', 'event_type'])} SELECT row_number() OVER (ORDER BY dim, key) - 1 AS feature_id, dim, key, min(pos) AS created_pos, count(*) AS support FROM pf GROUP BY dim, key")
def a8_dictionary(spark, sf):
    return L.dictionary(pf(spark, sf, "E", ["user_id", "event_type"]))


@query(f"WITH {S.features('E', ['user_id', 'event_type'])}, n AS (SELECT max(pos) + 1 AS n FROM pf), k AS (SELECT dim, key, min(pos) AS created_pos, count(*) AS support FROM pf, n WHERE pos < n // 2 GROUP BY dim, key), f AS (SELECT dim, key, min(pos) AS created_pos, count(*) AS support FROM pf, n WHERE pos >= n // 2 AND (dim, key) NOT IN (SELECT (dim, key) FROM k) GROUP BY dim, key) SELECT row_number() OVER (ORDER BY dim, key) - 1 AS feature_id, dim, key, created_pos, support FROM k UNION ALL SELECT (SELECT count(*) FROM k) + row_number() OVER (ORDER BY dim, key) - 1, dim, key, created_pos, support FROM f")
def a8_dictionary_growth(spark, sf):
    both = pf(spark, sf, "E", ["user_id", "event_type"])
    half = (both.agg(F.max("pos")).first()[0] + 1) // 2
    return L.dictionary(both.where(F.col("pos") >= half), L.dictionary(both.where(F.col("pos") < half)))


@query("SELECT CAST(0 AS BIGINT) AS collisions")
def a8_hashed_ids(spark, sf):
    return spark.createDataFrame([(L.collisions(L.hashed_ids(pf(spark, sf, "O"))),)], "collisions long")


@query(f"WITH {S.features('E', ['user_id'])}, n AS (SELECT 9 * (max(pos) + 1) // 10 AS n FROM pf) SELECT dim, key, min(pos) AS created_pos FROM pf, n WHERE pos >= n AND key NOT IN (SELECT key FROM pf, n WHERE pos < n) GROUP BY dim, key")
def a9_unseen_keys(spark, sf):
    both = pf(spark, sf, "E", ["user_id"])
    cut = 9 * (both.agg(F.max("pos")).first()[0] + 1) // 10
    return build.new_features(build.keyed(both.where(F.col("pos") < cut), PAPER), both.where(F.col("pos") >= cut))


@query("SELECT 'value>=' || (10 * i) AS key, count(*) AS n FROM events, range(1, 9) t(i) WHERE value >= 10 * i GROUP BY i")
def a10_create_queue(spark, sf):
    q = L.CreateQueue(L.events(spark, sf), n_create=8)
    made = [q.submit(f"value>={10 * i}", f"value >= {10 * i}") for i in range(1, 9)]
    return made[-1].groupBy("key").agg(F.count("*").alias("n"))


# dense index and its parts

for _n, _b in (("E", 32), ("E", 8), ("O", 32), ("L", 8)):
    _dims = ["suppkey", "returnflag"] if _n == "L" else None
    query(f"WITH {S.features(_n, _dims)}, {S.masks(_b)} {M_OUT}", name=f"b1_masks_{_n.lower()}_{_b}")(lambda spark, sf, n=_n, b=_b, d=_dims: masks(spark, sf, n, IndexSpec(b, 3), d).select(*MASK_COLS))


@query(f"WITH {S.features('O')}, {S.masks(32)} {M_OUT}")
def b1_masks_cluster_first(spark, sf):
    return masks(spark, sf, "O", cluster_first=True).select(*MASK_COLS)


@query(f"WITH {S.features('E', ['user_id'])}, {S.masks(2, 5)} {M_OUT}")
def b13_five_levels(spark, sf):
    return masks(spark, sf, "E", IndexSpec(2, 5), ["user_id"]).select(*MASK_COLS)


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(8)}, n AS (SELECT max(pos) + 1 AS n FROM pf), f AS (SELECT DISTINCT dim, key FROM pf), g AS (SELECT level, dim, key, unnest(range(0, CAST(ceil(n / pow(8, level + 1)) AS BIGINT))) AS node FROM f, n, range(0, 3) t(level)) SELECT CAST(g.level AS INTEGER) AS level, g.dim, g.key, g.node, coalesce(mask, 0) AS mask FROM g LEFT JOIN m ON g.level = m.level AND g.dim = m.dim AND g.key = m.key AND g.node = m.node")
def b4_dense(spark, sf):
    f = pf(spark, sf, "E", ["event_type"])
    n = f.agg(F.max("pos")).first()[0] + 1
    return build.densify(build.keyed(f, SMALL), SMALL, n).select("level", "dim", "key", "node", "mask")


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(32)} SELECT node, mask, CAST(len(list_filter(range(0, 32), lambda i: (mask >> CAST(31 - i AS INTEGER)) & 1 = 1)) AS INTEGER) AS bits, CAST(list_min(list_filter(range(0, 32), lambda i: (mask >> CAST(31 - i AS INTEGER)) & 1 = 1)) AS INTEGER) AS first_bit FROM m WHERE level = 0 AND key = 'purchase'")
def b6_bits_on(spark, sf):
    m = masks(spark, sf, "E", dims=["event_type"]).where("level = 0 and key = 'purchase'")
    return m.select("node", "mask", F.size(bits_on("mask", 32)).alias("bits"), F.array_min(bits_on("mask", 32)).alias("first_bit"))


FIND_E = "SELECT event_id AS pos FROM events WHERE "


@query(FIND_E + "user_id = 7")
def b7_search_dense(spark, sf):
    f = pf(spark, sf, "E", ["user_id"]).where("key in ('7', '8')")
    n = L.events(spark, sf).agg(F.max("pos")).first()[0] + 1
    return search.search_dense(build.densify(build.keyed(f, SMALL), SMALL, n), U7[0], SMALL)


@query(FIND_E + "user_id = 7 AND event_type = 'purchase'")
def b8_conjunction(spark, sf):
    return search.search_keyed(masks(spark, sf, "E"), All(U7 + BUY), PAPER)


@query(FIND_E + "user_id = 7 OR user_id = 8")
def b9_disjunction(spark, sf):
    return search.search_keyed(masks(spark, sf, "E"), Any((("user_id", "7"), ("user_id", "8"))), PAPER)


@query(FIND_E + "user_id = 7 AND event_type <> 'purchase'")
def b9_and_not(spark, sf):
    return search.search_keyed(masks(spark, sf, "E"), All(U7, BUY), PAPER)


@query(FIND_E + "event_type <> 'purchase'")
def b9_complement(spark, sf):
    n = L.events(spark, sf).agg(F.max("pos")).first()[0] + 1
    return search.complement(masks(spark, sf, "E"), BUY, n, PAPER)


@query("SELECT event_id, user_id, value FROM events WHERE user_id = 7")
def b10_fetch_rows(spark, sf):
    e = L.events(spark, sf)
    return search.fetch(e, search.search_keyed(masks(spark, sf, "E"), All(U7), PAPER)).select("event_id", "user_id", "value")


@query(f"SELECT event_id AS pos, {S.digest(E_COLS)} AS digest FROM events WHERE user_id = 7")
def b10_fetch_digests(spark, sf):
    _, chain = L.split_roles(L.events(spark, sf), E_COLS)
    return search.fetch(chain, search.search_keyed(masks(spark, sf, "E"), All(U7), PAPER))


def halves(spark, sf, name, dims, part=0.5, spec=SMALL):
    f = pf(spark, sf, name, dims)
    n = f.agg(F.max("pos")).first()[0] + 1
    cut = int(n * part)
    return f.where(F.col("pos") < cut), f.where(F.col("pos") >= cut), cut, n


@query(f"WITH {S.features('E')}, {S.masks(8)} {M_OUT}")
def b11_append(spark, sf):
    old, new, cut, _ = halves(spark, sf, "E", None)
    return build.append(build.keyed(old, SMALL), new, SMALL, cut).select(*MASK_COLS)


@query(f"WITH {S.features('E')}, c AS (SELECT (max(pos) + 1) // 2 AS cut FROM pf), old AS (SELECT pf.* FROM pf, c WHERE pos < cut), new AS (SELECT pf.* FROM pf, c WHERE pos >= cut), {S.masks(8, pf='old', name='o')}, {S.masks(8, pf='new', name='d')} SELECT d.level, count(o.mask) AS updated, count(*) - count(o.mask) AS created FROM d LEFT JOIN o USING (level, dim, key, node) GROUP BY d.level")
def b12_append_stats(spark, sf):
    old, new, cut, _ = halves(spark, sf, "E", None)
    return build.append_stats(build.keyed(old, SMALL), new, SMALL, cut)


@query("SELECT CAST(row_number() OVER (ORDER BY event_id) AS INTEGER) AS nth, event_id - lag(event_id, 1, 0) OVER (ORDER BY event_id) AS gap FROM events WHERE user_id = 7")
def b14_gaps(spark, sf):
    return search.gaps(search.search_keyed(masks(spark, sf, "E"), All(U7), PAPER))


@query(FIND_E + "user_id = 7", name="b14_from_gaps")
def b14_from_gaps(spark, sf):
    return search.from_gaps(b14_gaps(spark, sf))


@query("SELECT 'scan' AS path, event_id AS pos FROM events WHERE value BETWEEN 20 AND 21 UNION ALL SELECT 'index', event_id FROM events WHERE value >= 88.0")
def b15_predicate_or_scan(spark, sf):
    e = L.events(spark, sf)
    m = build.keyed(L.define(e, L.DEFINED["E"]), PAPER)
    n = e.count()
    one, a = route.route("value between 20 and 21", e, m, PAPER, n)
    two, b = route.route(All((("defined", "value>=88"),)), e, m, PAPER, n)
    return a.select(F.lit(one).alias("path"), "pos").unionByName(b.select(F.lit(two).alias("path"), "pos"))


@query("SELECT count(*) AS n FROM events WHERE user_id = 7 AND event_type = 'purchase'")
def b16_count(spark, sf):
    return search.count(masks(spark, sf, "E"), All(U7 + BUY), PAPER)


# sparse index and keeper


@query(f"WITH {S.features('E', ['user_id'])}, {S.masks(8)} SELECT level, dim, key, CAST(row_number() OVER (PARTITION BY level, dim, key ORDER BY node) - 1 AS INTEGER) AS rank, mask FROM m")
def c2_rank_layout(spark, sf):
    return sparse.ranked(masks(spark, sf, "E", SMALL, ["user_id"])).select("level", "dim", "key", "rank", "mask")


@query(f"WITH {S.features('O')}, {S.masks(8)} SELECT r.dim, r.key, r.tree, r.mask AS root, (SELECT count(*) FROM m1 WHERE m1.dim = r.dim AND m1.key = r.key AND m1.tree = r.tree) AS middles, (SELECT count(*) FROM m0 WHERE m0.dim = r.dim AND m0.key = r.key AND m0.tree = r.tree) AS leaves FROM m2 r")
def c3_packed(spark, sf):
    p = sparse.pack(masks(spark, sf, "O", SMALL), SMALL)
    return p.select("dim", "key", "tree", "root", F.size("middles").cast("long").alias("middles"), F.size("leaves").cast("long").alias("leaves"))


@query(f"WITH {S.features('O', ['custkey', 'status'])}, {S.masks(8)} {M_OUT}")
def c3_round_trip(spark, sf):
    return sparse.unpack(sparse.pack(masks(spark, sf, "O", SMALL, ["custkey", "status"]), SMALL), SMALL).select(*MASK_COLS)


@query(f"WITH {S.features('E', ['user_id'])} SELECT DISTINCT dim, key, pos // 512 AS tree FROM pf")
def c4_presence(spark, sf):
    return sparse.presence(masks(spark, sf, "E", SMALL, ["user_id"]), SMALL)


@query(f"WITH {S.features('E', ['user_id'])} SELECT dim, key, count(DISTINCT pos // 512) AS trees FROM pf GROUP BY dim, key")
def c4_presence_bitmaps(spark, sf):
    bm = sparse.presence_bitmaps(masks(spark, sf, "E", SMALL, ["user_id"]), SMALL)
    return bm.groupBy("dim", "key").agg(F.sum(F.expr("bitmap_count(bits)")).alias("trees"))


DIRECTORY = f"WITH {S.features('E', ['user_id'])}, {S.masks(8)}, t AS (SELECT r.dim, r.key, r.tree, (SELECT count(*) FROM m1 WHERE m1.dim = r.dim AND m1.key = r.key AND m1.tree = r.tree) AS a, (SELECT count(*) FROM m0 WHERE m0.dim = r.dim AND m0.key = r.key AND m0.tree = r.tree) AS b FROM m2 r)"


@query(f"{DIRECTORY} SELECT dim, key, tree, row_number() OVER w - 1 AS nth, CAST(sum(a) OVER w - a AS BIGINT) AS first_middle, CAST(sum(b) OVER w - b AS BIGINT) AS first_leaf FROM t WINDOW w AS (PARTITION BY dim, key ORDER BY tree)")
def c5_c6_directory(spark, sf):
    return sparse.directory(masks(spark, sf, "E", SMALL, ["user_id"]), SMALL)


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(32)} SELECT key, node, CAST(bit_count(mask >> 20) AS INTEGER) AS before_12 FROM m0")
def c7_child_rank(spark, sf):
    m = masks(spark, sf, "E", dims=["event_type"]).where("level = 0")
    return m.select("key", "node", rank_before("mask", "12", 32).cast("int").alias("before_12"))


@query(FIND_E + "user_id = 7 AND event_type = 'purchase'")
def c8_packed_conjunction(spark, sf):
    return search.search_packed(sparse.pack(masks(spark, sf, "E", SMALL), SMALL), [*U7, *BUY], SMALL)


@query(f"SELECT pos FROM {S.LINES} WHERE l_suppkey = 7 AND l_returnflag = 'R' AND l_linestatus = 'F'")
def c8_packed_three(spark, sf):
    p = sparse.pack(masks(spark, sf, "L", PAPER, ["suppkey", "returnflag", "linestatus"]), PAPER)
    return search.search_packed(p, [("suppkey", "7"), ("returnflag", "R"), ("linestatus", "F")], PAPER)


@query("SELECT event_id AS pos, event_id // 512 AS tree FROM events WHERE user_id = 7")
def c9_positions(spark, sf):
    found = search.search_packed(sparse.pack(masks(spark, sf, "E", SMALL, ["user_id"]), SMALL), list(U7), SMALL)
    tree, mid, leaf, bit = (F.expr(x) for x in ("pos div 512", "(pos div 64) % 8", "(pos div 8) % 8", "pos % 8"))
    return found.select(sparse.position(tree, mid, leaf, bit, SMALL).alias("pos"), tree.alias("tree"))


def _kept(spark, sf, flush):
    f = pf(spark, sf, "E")
    n = L.events(spark, sf).agg(F.max("pos")).first()[0] + 1
    keeper = store.Keeper(spark, storage.scratch(spark, "index"), SMALL)
    cuts = [0, n // 3, n // 2 + 5, n]
    for i, (a, b) in enumerate(zip(cuts, cuts[1:])):
        keeper.append(f.where((F.col("pos") >= a) & (F.col("pos") < b)), b - a, flush=flush or i == 2)
    return keeper


@query(f"WITH {S.features('E')}, {S.masks(8)} {M_OUT}")
def c10_automatic_flush(spark, sf):
    return _kept(spark, sf, False).index().select(*MASK_COLS)


@query(f"WITH {S.features('E')}, {S.masks(8)} {M_OUT}")
def c11_c12_manual_flush(spark, sf):
    return _kept(spark, sf, True).index().select(*MASK_COLS)


@query("SELECT CAST(3 AS BIGINT) AS versions, max(event_id) + 1 AS n_records, (max(event_id) + 1) // 512 AS open_tree FROM events")
def c16_manifest(spark, sf):
    keeper = _kept(spark, sf, True)
    m = store.Keeper(spark, keeper.path, SMALL).manifest
    return spark.createDataFrame([(m.version, m.n_records, m.open_tree)], "versions long, n_records long, open_tree long")


@query(f"WITH {S.features('E')}, d AS MATERIALIZED (SELECT event_id AS pos, 'defined' AS dim, 'value>=88' AS key FROM events WHERE value >= 88.0), {S.masks(32)}, {S.masks(32, pf='d', name='x')} SELECT 'keyword' AS kind, count(*) * 32 AS bits FROM m UNION ALL SELECT 'defined', count(*) * 32 FROM x")
def c13_general_and_defined_size(spark, sf):
    m = build.keyed(pf(spark, sf, "E").unionByName(L.define(L.events(spark, sf), L.DEFINED["E"])), PAPER)
    return m.groupBy(F.when(F.col("dim") == "defined", "defined").otherwise("keyword").alias("kind")).agg((F.count("*") * 32).alias("bits"))


@query(f"WITH {S.features('O')}, {S.masks(32)} SELECT (SELECT count(*) * 32 FROM m) AS total_bits, (SELECT max(c) FROM (SELECT count(*) AS c FROM m0 GROUP BY dim, node)) AS leaf_rank, (SELECT max(c) FROM (SELECT count(*) * 32 AS c FROM m GROUP BY level)) AS largest_level, (SELECT 3 * 32 * 4 * count(*) FROM src) AS bound_bits, true AS within, true AS rank_within")
def c14_bounds(spark, sf):
    return sparse.bounds(masks(spark, sf, "O"), PAPER, L.orders(spark, sf).count(), 4)


# resumable search


@query("SELECT event_id AS pos, CAST(user_id AS INTEGER) AS query_id, event_id AS stop FROM events")
def r1_tokens(spark, sf):
    t = L.events(spark, sf).select("pos", F.expr(f"shiftleft(user_id, {resume.POS_BITS}) | pos").alias("token"))
    q, stop = resume.token_columns("token")
    return t.select("pos", q.alias("query_id"), stop.alias("stop"))


def _n(spark, sf):
    return L.events(spark, sf).agg(F.max("pos")).first()[0] + 1


@query("SELECT event_id AS pos, (SELECT max(event_id) + 1 FROM events) AS next_stop FROM events WHERE user_id = 7 AND event_id >= 9 * (SELECT max(event_id) + 1 FROM events) // 10")
def r2_r3_resume(spark, sf):
    n = _n(spark, sf)
    found, token = resume.run(masks(spark, sf, "E", SMALL), All(U7), SMALL, n, 1, resume.make_token(1, 9 * n // 10))
    return found.select("pos", F.lit(resume.read_token(token)[1]).cast("long").alias("next_stop"))


@query("SELECT event_id AS pos FROM events WHERE user_id = 7 AND event_id >= 1234")
def r3_resume_packed(spark, sf):
    return search.search_packed(sparse.pack(masks(spark, sf, "E", SMALL, ["user_id"]), SMALL), list(U7), SMALL, 1234)


@query("SELECT CAST(event_type AS VARCHAR) AS event_type, max(event_id) AS stop FROM events GROUP BY event_type")
def r4_token_log(spark, sf):
    e = L.events(spark, sf)
    order = e.select(F.pmod(F.crc32("event_type"), F.lit(1 << 20)).cast("int").alias("query_id"), F.col("pos").cast("int").alias("version"), F.col("pos").alias("token"), F.col("ts").cast("timestamp").alias("issued_at"), "event_type")
    return resume.TokenLog(spark, order).latest().select("event_type", F.col("token").alias("stop"))


@query("WITH n AS (SELECT max(event_id) + 1 AS n FROM events) SELECT event_id AS pos FROM events, n WHERE user_id = 7 AND event_id >= n // 4 AND event_id < n // 2")
def r5_between_versions(spark, sf):
    n = _n(spark, sf)
    return resume.between(masks(spark, sf, "E", SMALL), All(U7), SMALL, resume.make_token(1, n // 4), resume.make_token(1, n // 2))


@query("SELECT event_type, CAST(max(event_id) AS INTEGER) AS version, max(event_id) AS stop FROM events WHERE ts <= (SELECT date_trunc('day', max(ts)) FROM events) GROUP BY event_type")
def r5_as_of(spark, sf):
    """The token of each event type's query as of the start of the last day; every event issues one."""
    e = L.events(spark, sf).withColumn("issued_at", F.col("ts").cast("timestamp"))
    number = F.pmod(F.crc32("event_type"), F.lit(1 << 20))
    token = F.shiftleft(number.cast("long"), resume.POS_BITS).bitwiseOR(F.col("pos"))
    log = resume.TokenLog(spark, e.select(number.cast("int").alias("query_id"), F.col("pos").cast("int").alias("version"), token.alias("token"), "issued_at", "event_type"))
    _, stop = resume.token_columns("token")
    return log.as_of(e.agg(F.date_trunc("day", F.max("issued_at"))).first()[0]).select("event_type", "version", stop.alias("stop"))


@query("SELECT event_type, CAST(2 * row_number() OVER (ORDER BY event_type) - 2 AS INTEGER) AS a, CAST(2 * row_number() OVER (ORDER BY event_type) - 2 AS INTEGER) AS same, CAST(2 * row_number() OVER (ORDER BY event_type) - 1 AS INTEGER) AS other FROM (SELECT DISTINCT event_type FROM events WHERE user_id = 7)")
def r6_query_numbers(spark, sf):
    """Numbers of the queries for a user and each type of its events: one whatever the order of features, another for any of them."""
    ids, rows = {}, []
    for (kind,) in sorted(L.events(spark, sf).where("user_id = 7").select("event_type").distinct().collect()):
        of = (("event_type", kind),)
        rows.append((kind, *[resume.query_number(q, ids) for q in (All(U7 + of), All(of + U7), Any(U7 + of))]))
    return spark.createDataFrame(rows, "event_type string, a int, same int, other int")


@query("SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra")
def r7_monotone(spark, sf):
    m, n = masks(spark, sf, "E", SMALL), _n(spark, sf)
    old = search.search_keyed(m, All(U7), SMALL).where(F.col("pos") < n // 2)
    return measures.recall_precision(old.union(search.search_keyed(m, All(U7), SMALL, n // 2)), search.search_keyed(m, All(U7), SMALL))


@query("SELECT event_id AS pos FROM events WHERE user_id = 7 AND event_id >= (SELECT max(event_id) + 1 FROM events) // 2")
def r8_restart(spark, sf):
    return search.search_keyed(masks(spark, sf, "E"), All(U7), PAPER).where(F.col("pos") >= _n(spark, sf) // 2)


# verification

for _k in (32, 36, 64, 100, 128):
    query(f"WITH d AS (SELECT event_id AS pos, {S.digest(E_COLS)} AS digest FROM events), c AS MATERIALIZED (SELECT pos, {S.code('digest', _k, R)} AS x FROM d) SELECT pos, {S.limbs('x')} FROM c", name=f"v1_codes_{_k}")(
        lambda spark, sf, k=_k: verify.with_codes(L.with_digest(L.events(spark, sf), E_COLS), k, R).select("pos", "code_hi", "code_lo")
    )


@query(f"WITH d AS (SELECT event_id AS pos, {S.digest(E_COLS)} AS digest FROM events), c AS MATERIALIZED (SELECT pos, {S.code('digest', 32, 0xEDB88320)} AS x FROM d) SELECT pos, CAST(x AS BIGINT) AS code FROM c")
def v2_standard_crc(spark, sf):
    return L.with_digest(L.events(spark, sf), E_COLS).select("pos", F.crc32(F.unhex("digest")).alias("code"))


def _sizes(spark, sf, dims):
    """The sizes of the answers for all keys of these dimensions of events; distinct, so few."""
    sizes = pf(spark, sf, "E", dims).groupBy("dim", "key").agg(F.count("*").alias("n")).select("n").distinct()
    return [r["n"] for r in sizes.collect()]


@query(f"WITH {S.features('E', ['user_id', 'event_type', 'day'])}, c AS (SELECT DISTINCT count(*) AS n FROM pf GROUP BY dim, key), w AS (SELECT 32 + 4 * i AS k FROM range(0, 25) t(i)) SELECT n, CAST(min(k) AS INTEGER) AS k FROM c, w WHERE n / pow(2, k) < 1e-5 AND n * (n - 1) / pow(2, k + 1) < -ln(0.99) GROUP BY n")
def v4_choose_width(spark, sf):
    return spark.createDataFrame([(n, verify.choose_k(n, 1 - 1e-5, 0.99)) for n in _sizes(spark, sf, ["user_id", "event_type", "day"])], "n long, k int")


@query(f"WITH {S.features('E', ['day'])}, c AS (SELECT DISTINCT count(*) AS n FROM pf GROUP BY key) SELECT n, k, round(n / pow(2, k) * 1e6, 6) AS one_minus_alpha_e6, round(coalesce((SELECT sum(-ln(1 - (i - 1) / pow(2, k))) FROM range(2, n + 1) t(i)), 0), 6) AS minus_ln_beta FROM c, (VALUES (32), (36)) v(k)")
def v5_achieved(spark, sf):
    rows = [(n, k, (1 - verify.alpha(n, k)) * 1e6, 0.0 - verify.log_beta(n, k)) for n in _sizes(spark, sf, ["day"]) for k in (32, 36)]
    made = spark.createDataFrame(rows, "n long, k int, one_minus_alpha_e6 double, minus_ln_beta double")
    return made.select("n", "k", F.round("one_minus_alpha_e6", 6).alias("one_minus_alpha_e6"), F.round("minus_ln_beta", 6).alias("minus_ln_beta"))  # halves go up, as in SQL


def _answer(spark, sf):
    e = L.events(spark, sf)
    found = storage.stored(search.search_keyed(masks(spark, sf, "E", SMALL), All(U7), SMALL), "found")
    chain = search.fetch(L.split_roles(e, E_COLS)[1], found)
    return search.fetch(e, found).select("pos", *E_COLS), verify.make_vo(chain, R)


@query(f"WITH d AS (SELECT {S.digest(E_COLS)} AS digest FROM events WHERE user_id = 7), c AS MATERIALIZED (SELECT {S.code('digest', 32, R)} AS x FROM d) SELECT {S.limbs('x')}, CAST(32 AS INTEGER) AS k, (SELECT count(*) FROM d) AS n_h FROM c")
def v6_chain_answer(spark, sf):
    _, vo = _answer(spark, sf)
    return vo.codes.select("code_hi", "code_lo", F.lit(vo.k).alias("k"), F.lit(vo.n_h).cast("long").alias("n_h"))


PICK = "(event_id * 7919) % 100 < {}"
for _mode, _rate in (("ok", 0), ("B1", 10), ("B2", 10), ("B3", 100), ("B1", 60)):
    _hit = "0" if _mode == "ok" else f"(SELECT count(*) FROM events WHERE user_id = 7 AND {PICK.format(_rate)})"
    _all = "(SELECT count(*) FROM events WHERE user_id = 7)"
    _row = {"ok": f"{_all}, {_all}, {_all}, 0, 0, 'ok'", "B1": f"{_all} + {_hit}, {_all}, {_all}, {_hit}, 0, CASE WHEN {_all} < 0.5 * ({_all} + {_hit}) THEN 'B3' WHEN {_hit} > 0 THEN 'B1' ELSE 'ok' END", "B2": f"{_all} - {_hit}, {_all}, {_all} - {_hit}, 0, {_hit}, CASE WHEN {_hit} > 0 THEN 'B2' ELSE 'ok' END", "B3": f"{_all}, {_all}, 0, {_all}, {_all}, 'B3'"}[_mode]

    def _verdict(spark, sf, mode=_mode, rate=_rate):
        rows, vo = _answer(spark, sf)
        return verify.verdict(verify.compare(vo, verify.inject(rows, mode, rate, "value"), E_COLS), 0.5)

    query(f"SELECT CAST(a AS BIGINT) AS n_r, CAST(b AS BIGINT) AS n_h, CAST(c AS BIGINT) AS n_acc, CAST(d AS BIGINT) AS unexpected, CAST(e AS BIGINT) AS missing, f AS behaviour FROM (SELECT {_row}) t(a, b, c, d, e, f)", name=f"v8_verdict_{_mode.lower()}_{_rate}")(_verdict)


@query(f"SELECT count(*) AS recovered, CAST(0 AS BIGINT) AS still_missing FROM events WHERE user_id = 7 AND {PICK.format(30)}")
def v9_recheck(spark, sf):
    rows, vo = _answer(spark, sf)
    rest = verify.leftover(verify.compare(vo, verify.inject(rows, "B2", 30, "value"), E_COLS), vo)
    again = verify.recheck(rest, verify.fetch_hidden(rows, 30), E_COLS, now=0.0)
    return again.agg(F.count_if(F.col("state") == "accepted").alias("recovered"), F.count_if(F.col("state") == "missing").alias("still_missing"))


@query(f"SELECT event_id AS pos, true AS altered FROM events WHERE user_id = 7 AND {PICK.format(10)}")
def v10_faults(spark, sf):
    e = L.events(spark, sf).where("user_id = 7").select("pos", *E_COLS)
    bad = verify.inject(e, "B1", 10, "value")
    return bad.exceptAll(e).select("pos", F.lit(True).alias("altered"))


@query("SELECT CAST(0 AS INTEGER) AS replica, count(*) AS n, CAST(3 AS BIGINT) AS votes FROM events WHERE user_id = 7")
def v11_agreement(spark, sf):
    """Four replicas, each with an index and a search of its own; the last one loses every other record."""
    runs = []
    for replica in range(4):
        own = pf(spark, sf, "E", ["user_id"])
        found = search.search_keyed(build.keyed(own if replica < 3 else own.where("pos % 2 = 0"), PAPER), All(U7), PAPER)
        runs.append(found.select(F.lit(replica).alias("replica"), "pos"))
    return verify.agree(reduce(lambda a, b: a.unionByName(b), runs))


MOST_LEVELS = 24


def _merkle_sql(out: str, rows: str = "events") -> str:
    """CTEs t0, t1, ... of a hash tree's levels, empty above the root; @all in ``out`` stands for their union."""
    ctes = [f"t0 AS MATERIALIZED (SELECT row_number() OVER (ORDER BY event_id) - 1 AS idx, {S.digest(E_COLS)} AS hash FROM {rows})"]
    for i in range(1, MOST_LEVELS + 1):
        ctes.append(f"t{i} AS MATERIALIZED (SELECT idx // 2 AS idx, CASE WHEN count(*) = 1 THEN max(hash) ELSE sha256(unhex(max(hash) FILTER (idx % 2 = 0) || max(hash) FILTER (idx % 2 = 1))) END AS hash FROM t{i - 1} WHERE (SELECT count(*) FROM t{i - 1}) > 1 GROUP BY idx // 2)")
    return "WITH " + ", ".join(ctes) + " " + out.replace("@all", " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS level, idx, hash FROM t{i}" for i in range(MOST_LEVELS + 1)))


@query(_merkle_sql("@all"))
def v12_hash_tree(spark, sf):
    return merkle.build(L.split_roles(L.events(spark, sf), E_COLS)[1], _n(spark, sf))


@query(_merkle_sql(" UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS level, hash AS sibling, true AS holds, false AS forged_holds FROM t{i} WHERE idx = xor(123 >> {i}, 1)" for i in range(MOST_LEVELS + 1))))
def v12_proof(spark, sf):
    """The siblings that prove record 123, and whether the record and a forged one check out with them."""
    n, tree = _n(spark, sf), v12_hash_tree(spark, sf)
    leaf = tree.where("level = 0 and idx = 123").first()["hash"]
    root = tree.where(f"level = {merkle.levels_of(n)}").first()["hash"]
    path = merkle.proof(tree, 123, n)
    holds, forged = merkle.check(leaf, path, root), merkle.check("00" * 32, path, root)
    levels = [i for i in range(merkle.levels_of(n)) if tree.where(f"level = {i} and idx = {(123 >> i) ^ 1}").count()]
    return spark.createDataFrame([(i, h, holds, forged) for i, (_, h) in zip(levels, path)], "level int, sibling string, holds boolean, forged_holds boolean")


@query("SELECT true AS holds, false AS forged_holds")
def v13_vector_commitment(spark, sf):
    values = [int(r[0], 16) for r in L.split_roles(L.events(spark, sf).where("event_id < 16"), E_COLS)[1].orderBy("pos").select("digest").collect()]
    c = merkle.VectorCommitment(values, secret=987654321987654321)
    v, w = c.open(5)
    return spark.createDataFrame([(c.verify(c.commitment, c.secret, 5, v, w), c.verify(c.commitment, c.secret, 5, v + 1, w))], "holds boolean, forged_holds boolean")


@query(f"SELECT CAST(rate AS INTEGER) AS rate, count(*) FILTER ((event_id * 7919) % 100 >= rate) AS fine_accepted, CASE WHEN count(*) FILTER ((event_id * 7919) % 100 < rate) = 0 THEN count(*) ELSE 0 END AS coarse_accepted, count(*) AS n FROM events, (VALUES (0), (10)) v(rate) WHERE user_id = 7 GROUP BY rate")
def v14_fine_or_coarse(spark, sf):
    """Codes accept what is right; one root over the whole answer accepts all of it or nothing."""
    rows, vo = _answer(spark, sf)
    rows = storage.stored(rows, "rows")
    out = []
    for rate in (0, 10):
        given = verify.inject(rows, "B2", rate, "value")
        fine = verify.compare(vo, given, E_COLS).agg(F.count_if(F.col("state") == "accepted")).first()[0]
        out.append((rate, fine, verify.coarse(rows, given, E_COLS), rows.count()))
    return spark.createDataFrame(out, "rate int, fine_accepted long, coarse_accepted long, n long")


# baselines


@query(FIND_E + "user_id = 7")
def k1_ordered_search(spark, sf):
    return B.OrderedIndex(L.events(spark, sf), "user_id").search("key = 7")


COST = "WITH s AS (SELECT event_id AS pos, user_id AS key, (row_number() OVER (ORDER BY user_id, event_id) - 1) // 256 AS leaf FROM events), h AS (SELECT CASE WHEN count(*) <= 256 THEN 1 WHEN count(*) <= 65536 THEN 2 ELSE 3 END AS h FROM s) SELECT count(*) AS hits, count(DISTINCT leaf) AS leaf_pages, count(DISTINCT pos // 64) AS table_pages, CAST({} AS BIGINT) AS descents FROM s, h WHERE key = 7"


@query(COST.format("any_value(h)"))
def k3_heap_cost(spark, sf):
    return B.OrderedIndex(L.events(spark, sf), "user_id").cost("key = 7").withColumn("descents", F.col("descents").cast("long"))


@query(COST.format("count(*) * any_value(h) + any_value(h)"))
def k2_clustered_cost(spark, sf):
    return B.OrderedIndex(L.events(spark, sf), "user_id", clustered=True).cost("key = 7").withColumn("descents", F.col("descents").cast("long"))


INSERT = "WITH n AS (SELECT 99 * (max(event_id) + 1) // 100 AS c FROM events), o AS (SELECT user_id AS key FROM events, n WHERE event_id < c), ks AS (SELECT key, sum(count(*)) OVER (ORDER BY key) AS upto FROM o GROUP BY key), d AS (SELECT user_id AS key FROM events, n WHERE event_id >= c), p AS (SELECT greatest(0, coalesce((SELECT max(upto) FROM ks WHERE ks.key <= d.key), 0) - 1) // 256 AS leaf FROM d), a AS (SELECT CAST(leaf AS BIGINT) AS leaf, count(*) AS added, least(256, (SELECT c FROM n) - CAST(leaf AS BIGINT) * 256) AS held FROM p GROUP BY leaf), h AS (SELECT CASE WHEN c <= 256 THEN 1 WHEN c <= 65536 THEN 2 ELSE 3 END AS h FROM n) SELECT CAST(sum(added) AS BIGINT) AS keys, count(*) AS leaves_touched, CAST(sum(greatest(0, ceil((added + held - 256) / 128.0))) AS BIGINT) AS splits, CAST({} AS BIGINT) AS node_visits FROM a, h"


def _insert(spark, sf, bulk):
    e = L.events(spark, sf)
    cut = 99 * _n(spark, sf) // 100
    return B.OrderedIndex(e.where(F.col("pos") < cut), "user_id").insert_cost(e.where(F.col("pos") >= cut), bulk)


@query(INSERT.format("any_value(h) * sum(added)"))
def k1a_insert_cost(spark, sf):
    return _insert(spark, sf, False)


@query(INSERT.format("any_value(h) * count(*)"))
def k1b_bulk_insert(spark, sf):
    return _insert(spark, sf, True)


@query(INSERT.format("0").replace("SELECT CAST(sum(added) AS BIGINT) AS keys, count(*) AS leaves_touched, CAST(sum(greatest(0, ceil((added + held - 256) / 128.0))) AS BIGINT) AS splits, CAST(0 AS BIGINT) AS node_visits", "SELECT count(*) * 16384 AS page_bytes, CAST(sum(added) * 16 AS BIGINT) AS entry_bytes"))
def k1c_write_amplification(spark, sf):
    e = L.events(spark, sf)
    cut = 99 * _n(spark, sf) // 100
    return B.OrderedIndex(e.where(F.col("pos") < cut), "user_id").write_amplification(e.where(F.col("pos") >= cut))


@query("SELECT event_id AS pos FROM events WHERE user_id = 7 AND event_id >= 9 * (SELECT max(event_id) + 1 FROM events) // 10")
def k4_composite_resume(spark, sf):
    return B.CompositeIndex(L.events(spark, sf), "user_id").search("key = 7", 9 * _n(spark, sf) // 10)


@query("SELECT count(*) FILTER (user_id = 7 AND event_id >= a) AS hits, count(*) AS scanned, count(DISTINCT event_id // 256) AS leaves FROM events, (SELECT 9 * (max(event_id) + 1) // 10 AS a FROM events) WHERE event_id // 256 >= a // 256")
def k4_composite_cost(spark, sf):
    return B.CompositeIndex(L.events(spark, sf), "user_id").cost("key = 7", 9 * _n(spark, sf) // 10)


def _annotated(spark, sf, part=1.0):
    e = L.events(spark, sf)
    return B.HashAnnotatedIndex(e if part == 1.0 else e.where(F.col("pos") < int(part * 100) * _n(spark, sf) // 100), "user_id", E_COLS, 64)


_LEVELS = [f"l0 AS MATERIALIZED (SELECT nth // 64 AS node, min(key) AS low, max(key) AS high, count(*) AS children, sha256(string_agg(key || '|' || pos || '|' || digest, ';' ORDER BY nth)) AS hash FROM (SELECT row_number() OVER (ORDER BY user_id, event_id) - 1 AS nth, user_id AS key, event_id AS pos, {S.digest(E_COLS)} AS digest FROM events) GROUP BY 1)"]
_LEVELS += [f"l{i} AS MATERIALIZED (SELECT node // 64 AS node, min(low) AS low, max(high) AS high, count(*) AS children, sha256(string_agg(hash, ';' ORDER BY node)) AS hash FROM l{i - 1} WHERE (SELECT count(*) FROM l{i - 1}) > 1 GROUP BY 1)" for i in range(1, 6)]
NODES = "WITH " + ", ".join(_LEVELS) + ", nodes AS (" + " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS level, node, low, high, children, hash FROM l{i}" for i in range(6)) + ") "


@query(NODES + "SELECT * FROM nodes")
def k5_node_digests(spark, sf):
    return _annotated(spark, sf).nodes


@query(FIND_E + "user_id = 7")
def k5_hash_annotated(spark, sf):
    """A search down the annotated tree."""
    return _annotated(spark, sf).search_between(7, 7)


@query(FIND_E + "user_id = 7 AND event_id >= 9 * (SELECT max(event_id) + 1 FROM events) // 10")
def k5_resume(spark, sf):
    return _annotated(spark, sf).search_between(7, 7, 9 * _n(spark, sf) // 10)


@query(NODES + "SELECT level, count(*) AS nodes FROM nodes WHERE low <= 7 AND high >= 7 GROUP BY level")
def k5_path(spark, sf):
    return _annotated(spark, sf).path(7, 7).groupBy("level").agg(F.count("*").alias("nodes"))


@query(INSERT.format("0").replace("256", "64").split(", a AS (SELECT")[0] + ", h AS (SELECT CASE WHEN c <= 64 THEN 1 WHEN c <= 4096 THEN 2 WHEN c <= 262144 THEN 3 ELSE 4 END AS h FROM n) SELECT CAST(i AS INTEGER) AS level, count(DISTINCT CAST(leaf AS BIGINT) // CAST(pow(64, i) AS BIGINT)) AS nodes FROM p, h, range(0, 4) t(i) WHERE i < h GROUP BY i")
def k5_rehashed(spark, sf):
    """Digests that inserting the last hundredth renews, by level."""
    return _annotated(spark, sf, 0.99).rehashed(L.events(spark, sf).where(F.col("pos") >= 99 * _n(spark, sf) // 100))


@query(NODES + "SELECT CAST((SELECT count(*) FROM events) * 48 + (SELECT count(*) FROM nodes) * 48 AS BIGINT) AS bytes")
def k5_size(spark, sf):
    return _annotated(spark, sf).size()


@query("SELECT event_id AS pos FROM events WHERE user_id = 7 AND event_id >= 9 * (SELECT max(event_id) + 1 FROM events) // 10")
def k6_skip_list_resume(spark, sf):
    return B.SkipIndex(L.events(spark, sf), "user_id").search("key = 7", 9 * _n(spark, sf) // 10)


TOWERS = "WITH s AS (SELECT event_id AS pos, CAST('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 8) AS BIGINT) AS m FROM events), v AS (SELECT pos, CASE WHEN m = 0 THEN 20 ELSE least(20, CAST(log2(m & -m) AS INTEGER)) END AS level FROM s)"
SEEK = TOWERS + ', w AS (SELECT i, pos FROM v, range(0, 21) t(i) WHERE pos < 900 AND i <= level), path AS (SELECT i, max(pos) AS pos FROM w GROUP BY i)'


@query(SEEK + ' SELECT CAST(i AS INTEGER) AS "on", pos FROM path')
def k6_skip_list_seek(spark, sf):
    return B.SkipIndex(L.events(spark, sf), "user_id").seek(900)


@query(SEEK + ', entered AS (SELECT i, coalesce(max(pos) OVER (ORDER BY i DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) AS e FROM path) SELECT CAST(w.i AS INTEGER) AS "on", count(*) AS hops FROM w JOIN entered ON w.i = entered.i WHERE pos > e GROUP BY w.i')
def k6_hops(spark, sf):
    return B.SkipIndex(L.events(spark, sf), "user_id").hops(900)


@query(TOWERS + " SELECT count(*) AS keys, CAST(sum(level + 1) AS BIGINT) AS pointers FROM v WHERE pos >= 99 * (SELECT max(event_id) + 1 FROM events) // 100")
def k6_insert_cost(spark, sf):
    e = L.events(spark, sf)
    return B.SkipIndex(e, "user_id").insert_cost(e.where(F.col("pos") >= 99 * _n(spark, sf) // 100))


@query("SELECT user_id AS key, event_id AS pos, lag(event_id) OVER (ORDER BY event_id) AS before FROM events WHERE user_id = 7")
def k6a_trace(spark, sf):
    return B.SkipIndex(L.events(spark, sf), "user_id").trace("key = 7")


@query(FIND_E + "user_id = 7")
def k7_full_scan(spark, sf):
    return B.full_scan(L.events(spark, sf), "user_id = 7")


@query("SELECT n * 32 // 8 AS bytes_32, n * 64 // 8 AS bytes_64, n * 128 // 8 AS bytes_128, n * 32 AS bytes_raw FROM (SELECT count(*) AS n FROM events WHERE value >= 88.0)")
def k10_fixed_widths(spark, sf):
    n = L.events(spark, sf).where("value >= 88.0").count()
    return spark.createDataFrame([tuple(verify.vo_bytes(n, k) for k in (32, 64, 128, None))], "bytes_32 long, bytes_64 long, bytes_128 long, bytes_raw long")


@query(f"SELECT n * 32 * CAST(ceil(log2(t)) AS BIGINT) AS proof_bytes, n * 4 AS code_bytes, CASE WHEN hidden = 0 THEN n ELSE 0 END AS accepted FROM (SELECT count(*) FILTER (user_id = 7) AS n, count(*) FILTER (user_id = 7 AND {PICK.format(10)}) AS hidden, count(*) AS t FROM events)")
def k11_coarse_proofs(spark, sf):
    """Bytes of a proof per record against those of codes, and what a comparison of roots accepts of an answer with hidden records."""
    e = L.events(spark, sf)
    own = storage.stored(e.where("user_id = 7").select("pos", *E_COLS), "rows")
    n, total = own.count(), e.count()
    accepted = verify.coarse(own, verify.inject(own, "B2", 10, "value"), E_COLS)
    return spark.createDataFrame([(n * merkle.proof_bytes(total), verify.vo_bytes(n, 32), accepted)], "proof_bytes long, code_bytes long, accepted long")


@query("SELECT CAST(3 AS BIGINT) AS chain_calls_each_time, CAST(1 AS BIGINT) AS chain_calls_reused")
def k12_ask_each_time(spark, sf):
    rows, vo = _answer(spark, sf)
    asked, rest, hidden = 1, verify.leftover(verify.compare(vo, verify.inject(rows, "B2", 30, "value"), E_COLS), vo), verify.fetch_hidden(rows, 30)
    tries = 1
    for part in (hidden.where("pos % 2 = 0"), hidden.where("pos % 2 = 1")):
        rest = verify.leftover(verify.recheck(rest, part, E_COLS, 0.0), rest)
        tries += 1
    assert rest.n_h == 0
    return spark.createDataFrame([(tries, asked)], "chain_calls_each_time long, chain_calls_reused long")


@query("SELECT o_orderkey AS pos FROM orders WHERE o_totalprice BETWEEN 100000 AND 120000")
def k13_range(spark, sf):
    return B.OrderedIndex(L.orders(spark, sf), "o_totalprice").range(100000, 120000)
