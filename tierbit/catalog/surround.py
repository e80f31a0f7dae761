"""Operators, sources and functions around the methods, on ledger, index or verification data."""

from __future__ import annotations

import json

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.catalog import query
from tierbit.catalog import sqltext as S
from tierbit.catalog.methods import E_COLS, R, U7, masks, pf
from tierbit.config import PAPER, SMALL
from tierbit.functions import udfs
from tierbit.functions.bits import bits_on
from tierbit.operators import build, search, sparse, verify
from tierbit.operators.search import All
from tierbit.sources import ledger as L
from tierbit.sources import storage
from tierbit.sources.packedsource import PackedSource

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def t(spark, sf, name):
    return L.table(spark, sf, name)


@query(" UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM {n}" for n in TABLES))
def src_parquet_schema(spark, sf):
    out = None
    for n in TABLES:
        one = t(spark, sf, n).agg(F.lit(n).alias("name"), F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT event_id, event_id AS row FROM events")
def src_row_index(spark, sf):
    return t(spark, sf, "events").select("event_id", F.col("_metadata.row_index").alias("row"))


def _round_trip(spark, sf, kind):
    path = storage.scratch(spark, kind)
    f = pf(spark, sf, "E", ["user_id", "event_type"])
    getattr(f.write.option("header", True) if kind == "csv" else f.write, kind)(path)
    reader = spark.read.schema("pos long, dim string, key string")
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


for _kind in ("json", "csv", "orc"):
    query(f"WITH {S.features('E', ['user_id', 'event_type'])} SELECT pos, dim, key FROM pf", name=f"src_{_kind}_round_trip")(lambda spark, sf, kind=_kind: _round_trip(spark, sf, kind))


@query("SELECT event_id AS pos FROM events WHERE user_id = 7")
def src_python_datasource(spark, sf):
    path = storage.scratch(spark, "packed")
    sparse.pack(masks(spark, sf, "E", SMALL, ["user_id"]), SMALL).repartitionByRange(4, "dim", "key").sortWithinPartitions("dim", "key", "tree").write.parquet(path)
    files = [r[0] for r in spark.read.parquet(path).select(F.input_file_name()).distinct().collect()]
    spark.dataSource.register(PackedSource)
    rows = spark.read.format("packed_index").option("files", json.dumps(files)).option("dim", "user_id").option("key", "7").option("push", spark.conf.get("spark.sql.python.filterPushdown.enabled", "false")).load()
    return search.search_packed(rows, list(U7), SMALL)


@query(f"WITH {S.features('O')}, {S.masks(32)} SELECT CAST(level AS INTEGER) AS level, count(*) AS masks FROM m GROUP BY level")
def sink_segments(spark, sf):
    path = storage.scratch(spark, "segments")
    masks(spark, sf, "O").repartition("dim", "key").sortWithinPartitions("dim", "key", "tree", "node").write.partitionBy("level").parquet(path)
    return spark.read.parquet(path).groupBy(F.col("level").cast("int").alias("level")).agg(F.count("*").alias("masks"))


@query("SELECT event_id AS pos FROM events")
def sink_noop(spark, sf):
    e = L.events(spark, sf).select("pos")
    e.write.format("noop").mode("overwrite").save()
    return e


@query("SELECT o_orderkey, o_totalprice * 2 AS doubled, CAST(o_custkey AS VARCHAR) AS cust, upper(o_orderstatus) AS status FROM orders")
def proj_bits(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", (F.col("o_totalprice") * 2).alias("doubled"), F.col("o_custkey").cast("string").alias("cust"), F.upper("o_orderstatus").alias("status"))


@query("SELECT o_orderkey, 'status' AS dim, o_orderstatus AS key FROM orders UNION ALL SELECT o_orderkey, 'priority', o_orderpriority FROM orders")
def proj_unpivot(spark, sf):
    o = t(spark, sf, "orders").select("o_orderkey", F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"))
    return o.unpivot("o_orderkey", ["status", "priority"], "dim", "key")


FILTERS = "l_returnflag = 'R' AND l_quantity BETWEEN 10 AND 20 AND l_linestatus IN ('F', 'O') AND NOT l_discount > 0.05 AND l_returnflag LIKE 'R%' AND l_shipdate IS NOT NULL AND (l_tax = 0.01 OR l_tax >= 0.04)"


@query(f"SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE {FILTERS}")
def filt_preds(spark, sf):
    return t(spark, sf, "lineitem").where(FILTERS).where(F.col("l_returnflag").eqNullSafe("R")).select("l_orderkey", "l_linenumber", "l_partkey")


@query(f"WITH {S.features('E')}, {S.masks(8)} SELECT a.dim, a.key, a.node, a.mask AS middle, b.node AS leaf, b.mask FROM m1 a JOIN m0 b ON a.dim = b.dim AND a.key = b.key AND a.node = b.node // 8")
def join_equi_levels(spark, sf):
    m = masks(spark, sf, "E", SMALL)
    a = m.where("level = 1").select("dim", "key", "node", F.col("mask").alias("middle"))
    b = m.where("level = 0").select("dim", "key", F.col("node").alias("leaf"), "mask").withColumn("node", F.expr("leaf div 8"))
    return a.join(b, ["dim", "key", "node"])


@query("SELECT o_orderstatus AS key, row_number() OVER (ORDER BY o_orderstatus) - 1 AS feature_id, count(*) AS n FROM orders GROUP BY o_orderstatus")
def join_broadcast_dict(spark, sf):
    f = pf(spark, sf, "O", ["status"])
    d = L.dictionary(f).select("dim", "key", "feature_id")
    return f.join(F.broadcast(d), ["dim", "key"]).groupBy("key", "feature_id").agg(F.count("*").alias("n"))  # three statuses: a bounded side


@query(f"SELECT pos, o_custkey, l_suppkey, p_name, c_acctbal < 0 AS negative FROM {S.STAR}")
def join_star14(spark, sf):
    return L.star(spark, sf).select("pos", "o_custkey", "l_suppkey", "p_name", (F.col("c_acctbal") < 0).alias("negative"))


@query("SELECT event_id FROM events WHERE EXISTS (SELECT 1 FROM events e WHERE e.user_id = events.user_id AND e.event_type = 'purchase')")
def join_semi_fetch(spark, sf):
    e = t(spark, sf, "events")
    return e.join(e.where("event_type = 'purchase'").select("user_id"), "user_id", "left_semi").select("event_id")


@query("SELECT count(DISTINCT t) AS n FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+')) AS t FROM documents) WHERE t <> '' AND t NOT IN (SELECT t FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+')) AS t FROM benchmark))")
def join_anti_newkeys(spark, sf):
    words = lambda n, k: L.extract_multi(t(spark, sf, n).withColumn("pos", F.col(k)), "text").select("key").distinct()
    return words("documents", "doc_id").join(words("benchmark", "item_id"), "key", "left_anti").agg(F.count("*").alias("n"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def join_outer_left(spark, sf):
    return t(spark, sf, "customer").join(t(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT doc_id, toxic FROM labels RIGHT JOIN documents USING (doc_id)")
def join_outer_right(spark, sf):
    return t(spark, sf, "labels").join(t(spark, sf, "documents"), "doc_id", "right").select("doc_id", "toxic")


@query("SELECT CASE WHEN (event_id * 7919) % 100 < 10 THEN 'missing' ELSE 'accepted' END AS state, count(*) AS n FROM events WHERE user_id = 7 GROUP BY 1")
def join_full_vo(spark, sf):
    e = L.events(spark, sf).where("user_id = 7").select("pos", *E_COLS)
    vo = verify.make_vo(L.with_digest(e, E_COLS).select("pos", "digest"), R)
    return verify.compare(vo, verify.inject(e, "B2", 10, "value"), E_COLS).groupBy("state").agg(F.count("*").alias("n"))


@query("SELECT event_id // 1000 AS segment, count(*) AS n FROM events WHERE value >= 88.0 GROUP BY 1")
def join_range_segments(spark, sf):
    """Positions to the segments that hold them: an equality on the bucket both sides share, then the range."""
    e = L.events(spark, sf).where("value >= 88.0").withColumn("bucket", F.expr("pos div 1000"))
    n = t(spark, sf, "events").count()
    seg = spark.range(-(-n // 1000)).select(F.col("id").alias("segment"), (F.col("id") * 1000).alias("first"), (F.col("id") * 1000 + 999).alias("last"), F.col("id").alias("bucket"))
    return e.join(seg, "bucket").where("pos between first and last").groupBy("segment").agg(F.count("*").alias("n"))


@query("SELECT a.event_id, max(b.event_id) AS token FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND b.event_id <= a.event_id GROUP BY a.event_id")
def join_asof_token(spark, sf):
    """The last purchase of the same user up to each event: a running maximum, not a range join."""
    upto = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, 0)
    e = t(spark, sf, "events")
    return e.select("event_id", F.max(F.when(F.col("event_type") == "purchase", F.col("event_id"))).over(upto).alias("token")).where("token is not null")


@query("SELECT c.event_id AS click, count(*) AS buys FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase' GROUP BY c.event_id")
def join_interval_events(spark, sf):
    e = t(spark, sf, "events")
    hour = lambda c: F.date_trunc("hour", c)
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t0"), F.explode(F.array(hour("ts"), hour("ts") + F.expr("INTERVAL 1 HOUR"))).alias("hour"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("t1"), hour("ts").alias("hour"))
    return c.join(p, ["user_id", "hour"]).where("t1 between t0 and t0 + INTERVAL 1 HOUR").groupBy("click").agg(F.count("*").alias("buys"))


@query("WITH n AS (SELECT max(event_id) + 1 AS n FROM events), k AS (SELECT event_id * 7 // n + 1 AS v, max(event_id) + 1 AS stop FROM events, n GROUP BY 1) SELECT a.v AS v1, b.v AS v2, b.stop - a.stop AS fresh FROM k a JOIN k b ON a.v < b.v")
def join_theta_tokens(spark, sf):
    """Pairs of token versions, oldest first, with the records between their stops: a version for each seventh of events."""
    e = t(spark, sf, "events").select("event_id")
    n = e.agg(F.max("event_id") + 1).first()[0]
    k = e.groupBy(F.expr(f"event_id * 7 div {n} + 1").alias("v")).agg((F.max("event_id") + 1).alias("stop"))
    a, b = (k.select(F.col("v").alias(f"v{i}"), F.col("stop").alias(f"stop{i}")) for i in (1, 2))
    return a.join(b, F.col("v1") < F.col("v2")).select("v1", "v2", (F.col("stop2") - F.col("stop1")).alias("fresh"))


@query("SELECT i AS prefix, k, i * n // 7 AS size FROM range(1, 8) a(i), (SELECT 'E' AS k, max(event_id) + 1 AS n FROM events UNION ALL SELECT 'O', max(o_orderkey) + 1 FROM orders) b")
def join_cross_grid(spark, sf):
    """The experiment grid: seven prefixes by two ledgers, with the records of each."""
    e, o = (L.ledger(spark, sf, n).agg(F.lit(n).alias("k"), (F.max("pos") + 1).alias("n")) for n in ("E", "O"))
    return spark.range(1, 8).select(F.col("id").alias("prefix")).crossJoin(e.unionByName(o)).select("prefix", "k", F.expr("prefix * n div 7").alias("size"))


for _f in ("bit_or", "bit_and", "bit_xor"):
    query(f"WITH {S.features('E')}, {S.masks(32)} SELECT dim, {_f}(mask) AS mask FROM m0 GROUP BY dim", name=f"agg_{_f}")(lambda spark, sf, f=_f: masks(spark, sf, "E").where("level = 0").groupBy("dim").agg(getattr(F, f)("mask").alias("mask")))


@query("SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, min(value) AS low, max(value) AS high, round(avg(value), 6) AS mean FROM events GROUP BY event_type")
def agg_basic(spark, sf):
    return t(spark, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"), F.min("value").alias("low"), F.max("value").alias("high"), F.round(F.avg("value"), 6).alias("mean"))


@query("SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
def agg_distinct(spark, sf):
    return t(spark, sf, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("SELECT true AS close FROM lineitem LIMIT 1")
def agg_approx_distinct(spark, sf):
    c = t(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"))
    return c.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("close"))


@query("SELECT l_returnflag, true AS close FROM lineitem GROUP BY l_returnflag")
def agg_percentile(spark, sf):
    c = t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.percentile_approx("l_extendedprice", 0.5, 10000).alias("a"), F.percentile("l_extendedprice", 0.5).alias("b"))
    return c.select("l_returnflag", (F.abs(F.col("a") - F.col("b")) <= 0.02 * F.col("b")).alias("close"))


@query("SELECT user_id, arg_max(event_type, event_id) AS latest FROM events GROUP BY user_id")
def agg_max_by(spark, sf):
    return t(spark, sf, "events").groupBy("user_id").agg(F.max_by("event_type", "event_id").alias("latest"))


@query(f"WITH {S.features('O', ['custkey'])}, {S.masks(8)} SELECT key, tree, count(*) AS leaves FROM m0 GROUP BY key, tree")
def agg_collect_packed(spark, sf):
    m = masks(spark, sf, "O", SMALL, ["custkey"]).where("level = 0")
    return m.groupBy("key", "tree").agg(F.size(F.collect_list("mask")).cast("long").alias("leaves"))  # 64 at most


@query("SELECT count(DISTINCT event_id // 512) AS trees FROM events WHERE user_id = 7")
def agg_bitmap_presence(spark, sf):
    x = t(spark, sf, "events").where("user_id = 7").select(F.expr("event_id div 512").alias("tree"))
    by = x.groupBy(F.expr("bitmap_bucket_number(tree)").alias("b")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(tree))").alias("bits"))
    return by.agg(F.sum(F.expr("bitmap_count(bits)")).alias("trees"))


SIZES = f"WITH {S.features('O')}, {S.masks(32)} SELECT dim, CAST(level AS INTEGER) AS level, count(*) AS n FROM m "


@query(SIZES + "GROUP BY ROLLUP (dim, level)")
def agg_rollup(spark, sf):
    return masks(spark, sf, "O").rollup("dim", "level").agg(F.count("*").alias("n"))


@query(SIZES + "GROUP BY CUBE (dim, level)")
def agg_cube(spark, sf):
    return masks(spark, sf, "O").cube("dim", "level").agg(F.count("*").alias("n"))


@query(SIZES + "GROUP BY GROUPING SETS ((dim), (level))")
def agg_grouping_sets(spark, sf):
    return masks(spark, sf, "O").groupingSets([["dim"], ["level"]], "dim", "level").agg(F.count("*").alias("n"))


@query(f"WITH {S.features('O')}, {S.masks(32)} SELECT dim, count(*) FILTER (level = 0) AS leaf, count(*) FILTER (level = 1) AS middle, count(*) FILTER (level = 2) AS root FROM m GROUP BY dim")
def agg_pivot(spark, sf):
    p = masks(spark, sf, "O").groupBy("dim").pivot("level", [0, 1, 2]).count()
    return p.select("dim", F.col("0").alias("leaf"), F.col("1").alias("middle"), F.col("2").alias("root"))


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(32)} SELECT key, node, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER v AS INTEGER) AS rk, CAST(dense_rank() OVER v AS INTEGER) AS dr FROM m0 WINDOW w AS (PARTITION BY key ORDER BY node), v AS (PARTITION BY key ORDER BY bit_count(mask))")
def win_rank_masks(spark, sf):
    m = masks(spark, sf, "E", dims=["event_type"]).where("level = 0")
    w, v = W.partitionBy("key").orderBy("node"), W.partitionBy("key").orderBy(F.bit_count("mask"))
    return m.select("key", "node", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"))


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(32)} SELECT key, node, CAST(coalesce(sum(bit_count(mask)) OVER (PARTITION BY key ORDER BY node ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before FROM m0")
def win_directory(spark, sf):
    w = W.partitionBy("key").orderBy("node").rowsBetween(W.unboundedPreceding, -1)
    return masks(spark, sf, "E", dims=["event_type"]).where("level = 0").select("key", "node", F.coalesce(F.sum(F.bit_count("mask")).over(w), F.lit(0)).cast("long").alias("before"))


@query("SELECT event_id, event_id - lag(event_id) OVER w AS gap, lead(event_id) OVER w - event_id AS ahead FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_lag_gaps(spark, sf):
    w = W.partitionBy("user_id").orderBy("event_id")
    return t(spark, sf, "events").select("event_id", (F.col("event_id") - F.lag("event_id").over(w)).alias("gap"), (F.lead("event_id").over(w) - F.col("event_id")).alias("ahead"))


@query("SELECT event_id, CAST(ntile(7) OVER w AS INTEGER) AS part, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM events WINDOW w AS (PARTITION BY event_type ORDER BY event_id)")
def win_ntile_prefix(spark, sf):
    w = W.partitionBy("event_type").orderBy("event_id")
    return t(spark, sf, "events").select("event_id", F.ntile(7).over(w).alias("part"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("SELECT event_id, count(*) OVER w AS last_hour, first_value(event_id) OVER w AS first_seen FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)")
def win_range_time(spark, sf):
    """Of events in the frame's first second the one with the smallest id was seen first: its order alone leaves that open."""
    w = W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    e = t(spark, sf, "events").withColumn("s", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000))
    return e.select("event_id", F.count("*").over(w).alias("last_hour"), F.min(F.struct("s", "event_id")).over(w)["event_id"].alias("first_seen"))


@query("SELECT o_custkey AS key, count(*) AS n FROM orders GROUP BY o_custkey ORDER BY n DESC, key LIMIT 10")
def sort_topk_features(spark, sf):
    return t(spark, sf, "orders").groupBy(F.col("o_custkey").alias("key")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "key").limit(10)


@query("SELECT event_id AS pos FROM events WHERE user_id = 7 ORDER BY pos LIMIT 5")
def limit_first_hits(spark, sf):
    return search.search_keyed(masks(spark, sf, "E", dims=["user_id"]), All(U7), PAPER).orderBy("pos").limit(5)


A_, B_ = "SELECT user_id FROM events WHERE event_type = 'purchase'", "SELECT user_id FROM events WHERE value >= 88.0"
for _op, _sql in (("union", "UNION"), ("unionAll", "UNION ALL"), ("intersect", "INTERSECT"), ("intersectAll", "INTERSECT ALL"), ("subtract", "EXCEPT"), ("exceptAll", "EXCEPT ALL")):

    def _set(spark, sf, op=_op):
        e = t(spark, sf, "events")
        a, b = e.where("event_type = 'purchase'").select("user_id"), e.where("value >= 88.0").select("user_id")
        return a.union(b).distinct() if op == "union" else getattr(a, op)(b)

    query(f"{A_} {_sql} {B_}", name=f"set_{_op.lower()}")(_set)


@query("SELECT page_id, regexp_extract(url, '://([^/:?]+)', 1) AS host, length(html) AS n, substr(lower(url), 1, 8) AS head, md5(url) AS mark FROM pages")
def fn_string(spark, sf):
    return t(spark, sf, "pages").select("page_id", F.regexp_extract("url", "://([^/:?]+)", 1).alias("host"), F.length("html").cast("long").alias("n"), F.substring(F.lower("url"), 1, 8).alias("head"), F.md5(F.col("url").cast("binary")).alias("mark"))


@query("SELECT conv_id, turn, role, sha256(text) AS digest, replace(role, 'a', 'A') AS role2, concat_ws('/', role, CAST(turn AS VARCHAR)) AS tag FROM conversations")
def fn_string_conversations(spark, sf):
    return t(spark, sf, "conversations").select("conv_id", "turn", "role", F.sha2(F.col("text").cast("binary"), 256).alias("digest"), F.regexp_replace("role", "a", "A").alias("role2"), F.concat_ws("/", "role", F.col("turn").cast("string")).alias("tag"))


@query("SELECT event_id, strftime(ts, '%Y-%m-%d') AS day, CAST(hour(ts) AS INTEGER) AS hour, strftime(date_trunc('month', ts), '%Y-%m-%d') AS month, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS days, epoch_us(ts) AS us FROM events")
def fn_date(spark, sf):
    return t(spark, sf, "events").select("event_id", F.date_format("ts", "yyyy-MM-dd").alias("day"), F.hour("ts").alias("hour"), F.date_format(F.date_trunc("month", "ts"), "yyyy-MM-dd").alias("month"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("days"), F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(32)} SELECT key, node, mask & 65535 AS low, mask | 1 AS set0, xor(mask, 255) AS x, mask >> 4 AS sh, CAST(bit_count(mask) AS INTEGER) AS bits, mask // 7 AS d, mask % 7 AS r, round(ln(1 + mask), 6) AS l FROM m0")
def fn_math_bits(spark, sf):
    m = masks(spark, sf, "E", dims=["event_type"]).where("level = 0")
    return m.selectExpr("key", "node", "mask & 65535L as low", "mask | 1L as set0", "mask ^ 255L as x", "shiftright(mask, 4) as sh", "cast(bit_count(mask) as int) as bits", "mask div 7 as d", "mask % 7 as r", "round(log1p(mask), 6) as l")


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(32)}, b AS (SELECT key, node, list_filter(range(0, 32), lambda i: (mask >> CAST(31 - i AS INTEGER)) & 1 = 1) AS v FROM m0) SELECT key, node, CAST(len(v) AS INTEGER) AS n, CAST(list_sum(v) AS BIGINT) AS total, CAST(v[1] AS INTEGER) AS first, list_contains(v, 0) AS has0, CAST(list_sum(list_transform(v[1:2], lambda x: x * x)) AS BIGINT) AS squares FROM b")
def fn_array(spark, sf):
    b = masks(spark, sf, "E", dims=["event_type"]).where("level = 0").select("key", "node", bits_on("mask", 32).alias("v"))
    return b.select("key", "node", F.size("v").alias("n"), F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.element_at("v", 1).alias("first"), F.array_contains("v", 0).alias("has0"), F.aggregate(F.transform(F.slice("v", 1, 2), lambda x: x * x), F.lit(0).cast("long"), lambda a, x: a + x).alias("squares"))


@query(f"WITH {S.features('E', ['user_id', 'event_type'])} SELECT pos, min(key) FILTER (dim = 'event_type') AS event_type, count(*) AS n FROM pf GROUP BY pos")
def fn_map(spark, sf):
    m = pf(spark, sf, "E", ["user_id", "event_type"]).groupBy("pos").agg(F.map_from_entries(F.collect_list(F.struct("dim", "key"))).alias("m"))
    return m.select("pos", F.col("m")["event_type"].alias("event_type"), F.size(F.map_keys("m")).cast("long").alias("n"))


@query("SELECT o_orderkey, CASE WHEN o_totalprice >= 417000 THEN 'high' WHEN o_orderstatus = 'F' THEN 'closed' ELSE coalesce(nullif(o_orderpriority, '1-URGENT'), 'now') END AS kind FROM orders")
def fn_case_null(spark, sf):
    s = t(spark, sf, "orders").select(F.struct("o_orderkey", "o_totalprice", "o_orderstatus", "o_orderpriority").alias("s"))
    return s.select("s.o_orderkey", F.when(F.col("s.o_totalprice") >= 417000, "high").when(F.col("s.o_orderstatus") == "F", "closed").otherwise(F.coalesce(F.nullif(F.col("s.o_orderpriority"), F.lit("1-URGENT")), F.lit("now"))).alias("kind"))


@query("SELECT event_id, CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) AS k, CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) AS k2 FROM events")
def fn_json(spark, sf):
    parsed = F.from_json("props", "k long")
    return t(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json(F.to_json(parsed), "k long")["k"].alias("k2"))


def sql_query(name: str, sql: str):
    """A query that is the same text in both engines."""

    def run(spark, sf):
        for n in ("events", "orders", "customer"):
            t(spark, sf, n).createOrReplaceTempView(n)
        return spark.sql(sql)

    query(sql, name=name)(run)


sql_query("sub_scalar", "SELECT event_id FROM events WHERE value > (SELECT avg(value) + 30 FROM events)")
sql_query("sub_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice >= 417000)")
sql_query("sub_correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(i.o_totalprice) * 1.5 FROM orders i WHERE i.o_custkey = o.o_custkey)")


@query("WITH leaf AS (SELECT event_id // 32 AS node, count(*) AS n FROM events WHERE user_id = 7 GROUP BY 1), middle AS (SELECT node // 32 AS node, count(*) AS leaves FROM leaf GROUP BY 1) SELECT node // 32 AS root, CAST(sum(leaves) AS BIGINT) AS leaves, count(*) AS middles FROM middle GROUP BY 1")
def cte_levels(spark, sf):
    t(spark, sf, "events").createOrReplaceTempView("events")
    return spark.sql("WITH leaf AS (SELECT event_id div 32 AS node, count(*) AS n FROM events WHERE user_id = 7 GROUP BY 1), middle AS (SELECT node div 32 AS node, count(*) AS leaves FROM leaf GROUP BY 1) SELECT node div 32 AS root, sum(leaves) AS leaves, count(*) AS middles FROM middle GROUP BY 1")


@query(f"WITH d AS (SELECT event_id AS pos, {S.digest(E_COLS)} AS digest FROM events), c AS MATERIALIZED (SELECT pos, {S.code('digest', 36, R)} AS x FROM d) SELECT pos, lpad(printf('%x', CAST(x AS BIGINT)), 9, '0') AS code FROM c")
def udf_crc_pandas(spark, sf):
    d = L.with_digest(L.events(spark, sf), E_COLS)
    return d.select("pos", udfs.code_udf(36, R)("digest").alias("code"))


@query(f"WITH {S.features('E', ['event_type'])} SELECT key, pos // 32 AS node, CAST(count(*) AS INTEGER) AS n, CAST(min(pos % 32) AS INTEGER) AS first FROM pf GROUP BY ALL")
def udf_debruijn(spark, sf):
    m = masks(spark, sf, "E", dims=["event_type"]).where("level = 0").select("key", "node", udfs.debruijn_bits("mask").alias("v"))
    return m.select("key", "node", F.size("v").alias("n"), F.element_at("v", 1).alias("first"))


@query(f"WITH {S.features('E')}, {S.masks(32)} SELECT dim, bit_or(mask) AS mask FROM m0 GROUP BY dim")
def udaf_mask_or(spark, sf):
    return masks(spark, sf, "E").where("level = 0").groupBy("dim").agg(udfs.mask_or("mask").alias("mask"))


@query("SELECT event_id AS pos FROM events WHERE user_id = 7")
def udtf_decode(spark, sf):
    udfs.register(spark)
    masks(spark, sf, "E", dims=["user_id"]).where("level = 0 and key = '7'").createOrReplaceTempView("tb_leaves")
    return spark.sql("SELECT d.pos FROM tb_leaves, LATERAL tb_decode(node, mask, 32) d")


@query(f"WITH {S.features('E', ['event_type'])}, {S.masks(32)} SELECT key, node, CAST(bit_count(mask) AS INTEGER) AS n, CAST(bit_count(mask >> 16) AS INTEGER) AS before_16 FROM m0")
def sql_functions(spark, sf):
    udfs.register(spark)
    masks(spark, sf, "E", dims=["event_type"]).where("level = 0").createOrReplaceTempView("tb_types")
    return spark.sql("SELECT key, node, size(tb_bits_on(mask)) AS n, tb_rank(mask, 16) AS before_16 FROM tb_types")


@query("SELECT label, count(*) AS n, count(DISTINCT vec_id) AS vectors FROM embeddings GROUP BY label")
def emb_digest(spark, sf):
    e = t(spark, sf, "embeddings").select(F.col("vec_id").alias("pos"), "label", F.sha2(F.to_json(F.struct("embedding")).cast("binary"), 256).alias("digest"))
    m = build.keyed(L.extract(e, {"label": "label"}), PAPER).where("level = 0")
    n = m.groupBy(F.col("key").cast("int").alias("label")).agg(F.sum(F.bit_count("mask")).alias("n"))
    return n.join(e.where("length(digest) = 64").groupBy("label").agg(F.count_distinct("pos").alias("vectors")), "label")
