"""Ledgers: append-only tables with a gap-free position, their digests, roles and features."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tierbit.sources.storage import stored

DAY = "yyyy-MM-dd"
LINE_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"]
#: Dimensions of each ledger: name and SQL expression of the key.
DIMS = {
    "E": {"user_id": "user_id", "event_type": "event_type", "k": "get_json_object(props, '$.k')", "day": f"date_format(ts, '{DAY}')"},
    "O": {"custkey": "o_custkey", "status": "o_orderstatus", "priority": "o_orderpriority", "orderdate": f"date_format(o_orderdate, '{DAY}')"},
    "L": {"suppkey": "l_suppkey", "partkey": "l_partkey", "returnflag": "l_returnflag", "linestatus": "l_linestatus", "quantity": "cast(l_quantity as int)", "shipdate": f"date_format(l_shipdate, '{DAY}')"},
    "L14": {
        "from": "o_custkey", "to": "l_suppkey", "to_create": "l_partkey", "from_contract": "c_acctbal < 0", "to_contract": "c_nationkey = s_nationkey", "value": "l_extendedprice", "gas_limit": "cast(l_quantity as int)",
        "gas_price": f"date_format(l_shipdate, '{DAY}')", "gas_used": f"date_format(o_orderdate, '{DAY}')", "function": "p_name", "is_error": "l_returnflag = 'R'", "type": "l_linestatus", "max_fee": "l_discount > 0.05", "max_priority": "l_tax > 0.04",
    },
}
#: Predicates registered as features of their own.
DEFINED = {"E": {"value>=88": "value >= 88.0"}, "O": {"price>=417000": "o_totalprice >= 417000"}, "L": {"price>=87700": "l_extendedprice >= 87700"}}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def with_rank(df: DataFrame, order: list[str], name: str = "pos", partitions: int | None = None, columns: list[str] | None = None) -> DataFrame:
    """Gap-free rank in a total order without a single-task sort: ranges, then each range's offset.

    Range boundaries are sampled anew in every job, so the ranges are written once, ``columns``
    of them only if given; only one count per range reaches the driver.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    ranged = stored(ranged if columns is None else ranged.select("_at", *columns), "ranged")
    ranged = ranged.withColumn("_part", F.shiftright("_at", 33))
    offsets = _offsets(ranged, "_part", "long")
    return ranged.join(F.broadcast(offsets), "_part").withColumn(name, F.col("_offset") + F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_at", "_part", "_offset")


def _offsets(parts: DataFrame, col: str, kind: str) -> DataFrame:
    """Rows before each part, one small row for each range or file: the only table that is broadcast here."""
    rows, seen = [], 0
    for p, n in sorted((r[0], r[1]) for r in parts.groupBy(col).count().collect()):
        rows.append((p, seen))
        seen += n
    return parts.sparkSession.createDataFrame(rows, f"{col} {kind}, _offset long")


def with_file_positions(df: DataFrame, name: str = "pos") -> DataFrame:
    """Positions by file and row within it: no shuffle; one count per file reaches the driver."""
    marked = df.select("*", F.col("_metadata.file_path").alias("_file"), F.col("_metadata.row_index").alias("_row"))
    offsets = _offsets(marked, "_file", "string")
    return marked.join(F.broadcast(offsets), "_file").withColumn(name, F.col("_offset") + F.col("_row")).drop("_file", "_row", "_offset")


def events(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "events").withColumn("pos", F.col("event_id"))


def orders(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "orders").withColumn("pos", F.col("o_orderkey"))


def lines(spark, sf_dir, columns: list[str] | None = None) -> DataFrame:
    return with_rank(table(spark, sf_dir, "lineitem"), LINE_ORDER, columns=columns)


def star(spark, sf_dir, columns: list[str] | None = None) -> DataFrame:
    """The fourteen-dimension ledger; dimension tables join by Spark's own choice of strategy. With ``columns`` (and
    pos) of it only, nothing else of the lines is ranked and written."""
    t = lambda n: table(spark, sf_dir, n)
    if columns is not None:
        own = [c for c in t("lineitem").columns if c in {*columns, "l_orderkey", "l_suppkey", "l_partkey"}]
        return _star(t, lines(spark, sf_dir, own)).select("pos", *columns)
    return _star(t, lines(spark, sf_dir))


def _star(t, rows: DataFrame) -> DataFrame:
    return rows.join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))


LEDGERS = {"E": events, "O": orders, "L": lines, "L14": star}


def ledger(spark, sf_dir, name: str) -> DataFrame:
    return LEDGERS[name](spark, sf_dir)


def extract(df: DataFrame, dims: dict[str, str]) -> DataFrame:
    """(pos, dim, key): one row per record and single-valued dimension; null keys make no feature."""
    pairs = F.array(*[F.struct(F.lit(d).alias("dim"), F.expr(e).cast("string").alias("key")) for d, e in dims.items()])
    return df.select("pos", F.explode(pairs).alias("f")).select("pos", "f.dim", "f.key").where("key is not null")


TOKEN_SPLIT = r"[^\p{L}\p{N}]+"


def extract_multi(df: DataFrame, col: str, dim: str = "token") -> DataFrame:
    """(pos, dim, key) of a keyword-set dimension: distinct lower-case runs of letters and digits."""
    words = F.array_distinct(F.split(F.lower(F.col(col)), TOKEN_SPLIT))
    return df.select("pos", F.explode(words).alias("key")).where("key <> ''").select("pos", F.lit(dim).alias("dim"), "key")


def define(df: DataFrame, predicates: dict[str, str]) -> DataFrame:
    """(pos, dim, key) of user-defined predicates, all in one scan."""
    hits = F.filter(F.array(*[F.when(F.expr(p), F.lit(n)) for n, p in predicates.items()]), lambda x: x.isNotNull())
    return df.select("pos", F.explode(hits).alias("key")).select("pos", F.lit("defined").alias("dim"), "key")


class CreateQueue:
    """Collects predicates and creates their features in one scan once ``n_create`` wait (or by force)."""

    def __init__(self, df: DataFrame, n_create: int):
        self.df, self.n_create, self.waiting, self.scans = df, n_create, {}, 0

    def submit(self, name: str, predicate: str, force: bool = False) -> DataFrame | None:
        self.waiting[name] = predicate
        if len(self.waiting) < self.n_create and not force:
            return None
        made, self.waiting, self.scans = define(self.df, self.waiting), {}, self.scans + 1
        return made


def supported(pf: DataFrame, least: dict[str, int], default: int = 1) -> DataFrame:
    """Only features with enough records in their dimension."""
    floor = F.lit(default)
    for dim, n in least.items():
        floor = F.when(F.col("dim") == dim, n).otherwise(floor)
    kept = pf.groupBy("dim", "key").count().where(F.col("count") >= floor).select("dim", "key")
    return pf.join(kept, ["dim", "key"], "left_semi")


def dictionary(pf: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """feature_id, dim, key, created_pos, support; new keys follow the known ones' ids."""
    keys = pf.groupBy("dim", "key").agg(F.min("pos").alias("created_pos"), F.count("*").alias("support"))
    if known is None:
        return with_rank(keys, ["dim", "key"], "feature_id").select("feature_id", "dim", "key", "created_pos", "support")
    top = known.agg(F.coalesce(F.max("feature_id"), F.lit(-1))).first()[0]
    fresh = with_rank(keys.join(known, ["dim", "key"], "left_anti"), ["dim", "key"], "feature_id")
    return known.unionByName(fresh.withColumn("feature_id", F.col("feature_id") + top + 1).select(known.columns))


def hashed_ids(pf: DataFrame) -> DataFrame:
    """The 64-bit hash alternative to the dictionary: feature_id, dim, key. Check ``collisions`` before use."""
    return pf.select("dim", "key").distinct().select(F.xxhash64("dim", "key").alias("feature_id"), "dim", "key")


def collisions(ids: DataFrame) -> int:
    return ids.groupBy("feature_id").count().where("count > 1").count()


def digest(cols: list[str]) -> Column:
    """SHA-256 over the columns' text joined by a bar, in lower-case hex."""
    return F.sha2(F.concat_ws("|", *[F.col(c).cast("string") for c in cols]).cast("binary"), 256)


def with_digest(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.withColumn("digest", digest(cols))


def split_roles(df: DataFrame, cols: list[str]) -> tuple[DataFrame, DataFrame]:
    """(provider: pos and content, chain: pos and digest)."""
    return df.select("pos", *cols), with_digest(df, cols).select("pos", "digest")


