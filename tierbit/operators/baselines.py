"""Baselines as Spark access paths for the same questions, with counted costs.

Each has build, search (with ``after``: only records from that position), insert cost and
storage. Costs are pages, nodes, splits and hashes: engine-independent, unlike latencies.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.sources.ledger import digest, with_rank
from tierbit.sources.storage import stored


class OrderedIndex:
    """A secondary B+-tree: entries sorted by (key, pos) in leaves of ``fanout``, rows looked up in pages."""

    def __init__(self, ledger: DataFrame, key: str, fanout: int = 256, page_rows: int = 64, clustered: bool = False):
        self.key, self.fanout, self.page_rows, self.clustered = key, fanout, page_rows, clustered
        entries = ledger.select(F.expr(key).alias("key"), "pos").where("key is not null")
        self.entries = with_rank(entries, ["key", "pos"], "at").withColumn("leaf", F.expr(f"at div {fanout}"))
        self.n = self.entries.count()

    @property
    def height(self) -> int:
        leaves, levels = max(1, math.ceil(self.n / self.fanout)), 1
        while leaves > 1:
            leaves, levels = math.ceil(leaves / self.fanout), levels + 1
        return levels

    def search(self, condition: str, after: int = 0) -> DataFrame:
        """pos of entries whose ``key`` satisfies the condition; the index itself can't skip old ones."""
        found = self.entries.where(condition)
        return (found.where(F.col("pos") >= after) if after else found).select("pos")

    def range(self, low, high) -> DataFrame:
        return self.entries.where(F.col("key").between(low, high)).select("pos")

    def cost(self, condition: str) -> DataFrame:
        """hits, leaf_pages, table_pages, descents: a clustered table goes through its id index once more per hit."""
        found = self.entries.where(condition)
        return found.agg(F.count("*").alias("hits"), F.count_distinct("leaf").alias("leaf_pages"), F.count_distinct(F.expr(f"pos div {self.page_rows}")).alias("table_pages")).withColumn("descents", F.when(F.lit(self.clustered), F.col("hits") * self.height).otherwise(0) + self.height)

    def insert_cost(self, batch: DataFrame, bulk: bool = False) -> DataFrame:
        """keys, leaves touched, splits, node visits for a batch.

        A key goes after all entries up to it: their number is its rank among old and new
        less its rank among the new, so no task holds the whole order. A leaf that overflows
        splits as often as it needs. Bulk insertion walks to each touched leaf once.
        """
        return self.split_cost(self.placed(batch), bulk)

    def split_cost(self, leaves: DataFrame, bulk: bool = False) -> DataFrame:
        """The same from the leaves that new keys go to."""
        placed = leaves.groupBy("leaf").agg(F.count("*").alias("added"))
        held = F.least(F.lit(self.fanout), F.lit(self.n) - F.col("leaf") * self.fanout)
        splits = F.greatest(F.lit(0), F.ceil((F.col("added") + held - self.fanout) / (self.fanout / 2)))
        visits = F.lit(self.height) * (F.count("*") if bulk else F.sum("added"))
        return placed.agg(F.sum("added").alias("keys"), F.count("*").alias("leaves_touched"), F.sum(splits).cast("long").alias("splits"), visits.cast("long").alias("node_visits"))

    def write_amplification(self, batch: DataFrame, page_bytes: int = 16384, entry_bytes: int = 16) -> DataFrame:
        """Bytes of rewritten leaf pages against bytes of new entries."""
        c = self.insert_cost(batch)
        return c.select((F.col("leaves_touched") * page_bytes).alias("page_bytes"), (F.col("keys") * entry_bytes).alias("entry_bytes"))

    def storage(self, entry_bytes: int = 16) -> int:
        return self.n * entry_bytes

    def hashes_per_insert(self) -> int:
        """For the hash-annotated form: node hashes renewed from leaf to root."""
        return self.height

    def renewed(self, leaves: DataFrame) -> DataFrame:
        """level, nodes: the touched leaves and all nodes above them, each once."""
        up = F.explode(F.array(*[F.struct(F.lit(i).alias("level"), F.expr(f"leaf div {self.fanout**i}").alias("node")) for i in range(self.height)]))
        return leaves.distinct().select(up.alias("x")).groupBy("x.level").agg(F.count_distinct("x.node").alias("nodes"))

    def placed(self, batch: DataFrame) -> DataFrame:
        """The leaf, among the present ones, that each new key goes to."""
        new = batch.select(F.expr(self.key).alias("key"), F.lit(1).alias("new"), "pos").where("key is not null")
        mixed = with_rank(self.entries.select("key", F.lit(0).alias("new"), "pos").unionByName(new), ["key", "new", "pos"], "all_at").where("new = 1")
        before = with_rank(new, ["key", "pos"], "new_at").select("pos", "new_at")
        return mixed.join(before, "pos").select(F.expr(f"greatest(0, all_at - new_at - 1) div {self.fanout}").alias("leaf"))


class HashAnnotatedIndex(OrderedIndex):
    """An ordered index whose nodes carry digests: a leaf's over its entries (key, position, record digest), an inner node's over its children's."""

    def __init__(self, ledger: DataFrame, key: str, cols: list[str], fanout: int = 256, page_rows: int = 64):
        super().__init__(ledger, key, fanout, page_rows)
        digests = ledger.select("pos", digest(cols).alias("digest"))
        self.entries = stored(self.entries.join(digests, "pos"), "annotated")
        self.nodes = self._annotate()

    def _annotate(self) -> DataFrame:
        """(level, node, low, high, children, hash), level 0 are the leaves."""
        text = F.concat_ws("|", F.col("key").cast("string"), F.col("pos").cast("string"), "digest")
        ordered = lambda at, x: F.array_join(F.transform(F.array_sort(F.collect_list(F.struct(at, x.alias("x")))), lambda e: e["x"]), ";")
        level = self.entries.groupBy(F.col("leaf").alias("node")).agg(F.min("key").alias("low"), F.max("key").alias("high"), F.count("*").alias("children"), F.sha2(ordered("at", text), 256).alias("hash"))
        out = [stored(level, "nodes")]
        for _ in range(1, self.height):
            level = out[-1].groupBy(F.expr(f"node div {self.fanout}").alias("node_")).agg(F.min("low").alias("low"), F.max("high").alias("high"), F.count("*").alias("children"), F.sha2(ordered("node", F.col("hash")), 256).alias("hash")).withColumnRenamed("node_", "node")
            out.append(stored(level, "nodes"))
        return reduce(DataFrame.unionByName, [x.select(F.lit(i).alias("level"), "node", "low", "high", "children", "hash") for i, x in enumerate(out)])

    def path(self, low, high) -> DataFrame:
        """The nodes that a search for keys from low to high visits, from the root down."""
        out, above = [], None
        for level in range(self.height - 1, -1, -1):
            own = self.nodes.where((F.col("level") == level) & (F.col("low") <= high) & (F.col("high") >= low))
            if above is not None:
                own = own.join(above, F.expr(f"node div {self.fanout}") == F.col("up"), "left_semi")
            out.append(own)
            above = own.select(F.col("node").alias("up"))
        return reduce(DataFrame.unionByName, out)

    def search_between(self, low, high, after: int = 0) -> DataFrame:
        """pos of the entries in the leaves that the descent ends at; the index itself can't skip old ones."""
        leaves = self.path(low, high).where("level = 0").select(F.col("node").alias("leaf"))
        found = self.entries.join(leaves, "leaf", "left_semi").where(F.col("key").between(low, high))
        return (found.where(F.col("pos") >= after) if after else found).select("pos")

    def rehashed(self, batch: DataFrame) -> DataFrame:
        """level, nodes: digests that a batch renews, each node once."""
        return self.renewed(stored(self.placed(batch), "touched"))

    def size(self, key_bytes: int = 8, pos_bytes: int = 8, hash_bytes: int = 32) -> DataFrame:
        """bytes: entries with their digests, nodes with digest, low key and child pointer."""
        nodes = self.nodes.agg(F.count("*").alias("n"))
        return nodes.select((F.lit(self.n * (key_bytes + pos_bytes + hash_bytes)) + F.col("n") * (hash_bytes + key_bytes + pos_bytes)).cast("long").alias("bytes"))


class CompositeIndex:
    """Entries sorted by (position, key) in leaves: a resumed search seeks the first new id, then walks and filters."""

    def __init__(self, ledger: DataFrame, key: str, fanout: int = 256):
        self.fanout = fanout
        entries = with_rank(ledger.select("pos", F.expr(key).alias("key")), ["pos", "key"], "at")
        self.entries = entries.withColumn("leaf", F.expr(f"at div {fanout}"))
        self.n = self.entries.count()

    def seek(self, after: int) -> int:
        """The leaf where the first entry from ``after`` on lies, by the leaves' first positions."""
        firsts = self.entries.groupBy("leaf").agg(F.min("pos").alias("first"))
        return firsts.where(F.col("first") <= after).agg(F.coalesce(F.max("leaf"), F.lit(0))).first()[0]

    def search(self, condition: str, after: int = 0) -> DataFrame:
        walked = self.entries.where(F.col("leaf") >= self.seek(after)) if after else self.entries
        return walked.where(F.col("pos") >= after).where(condition).select("pos")

    def scanned(self, after: int) -> DataFrame:
        return self.entries.where(F.col("pos") >= after).agg(F.count("*").alias("scanned"))

    def cost(self, condition: str, after: int) -> DataFrame:
        """hits, entries scanned, leaves walked."""
        walked = self.entries.where(F.col("leaf") >= self.seek(after))
        hit = F.expr(condition) & (F.col("pos") >= after)
        return walked.agg(F.count_if(hit).alias("hits"), F.count("*").alias("scanned"), F.count_distinct("leaf").alias("leaves"))

    def storage(self, pos_bytes: int = 8, key_bytes: int = 8, pointer_bytes: int = 8) -> int:
        return self.n * (pos_bytes + key_bytes + pointer_bytes)


class SkipIndex:
    """An append-only skip list on id with keys in its nodes: a node's height is the number of trailing zeros of a hash."""

    def __init__(self, ledger: DataFrame, key: str, max_level: int = 20):
        mark = F.conv(F.substring(F.md5(F.col("pos").cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
        zeros = F.when(mark == 0, max_level).otherwise(F.least(F.log2(mark.bitwiseAND(-mark)).cast("int"), F.lit(max_level)))
        self.nodes = ledger.select("pos", F.expr(key).alias("key"), zeros.alias("level"))
        self.max_level = max_level

    def seek(self, target: int) -> DataFrame:
        """The last node before ``target`` on each level, top first: the path of a seek."""
        return self.nodes.where(F.col("pos") < target).select("pos", F.explode(F.sequence(F.lit(0), "level")).alias("on")).groupBy("on").agg(F.max("pos").alias("pos")).orderBy(F.desc("on"))

    def hops(self, target: int) -> DataFrame:
        """on, hops: nodes walked on each level of a seek, from where the level above left off."""
        path = self.seek(target).withColumn("entered", F.coalesce(F.max("pos").over(W.orderBy(F.desc("on")).rowsBetween(W.unboundedPreceding, -1)), F.lit(-1)))  # a row per level
        walked = self.nodes.where(F.col("pos") < target).select("pos", F.explode(F.sequence(F.lit(0), "level")).alias("on"))
        return walked.join(F.broadcast(path.select("on", "entered")), "on").where("pos > entered").groupBy("on").agg(F.count("*").alias("hops"))

    def search(self, condition: str, after: int = 0) -> DataFrame:
        """Down the towers to the last node before ``after``, then along the lowest level."""
        start = 0
        if after:
            bottom = self.seek(after).where("on = 0").first()
            start = bottom["pos"] + 1 if bottom else 0
        return self.nodes.where(F.col("pos") >= start).where(condition).select("pos")

    def insert_cost(self, batch: DataFrame) -> DataFrame:
        """keys, pointers: a node appended at the end links once on each of its levels."""
        own = SkipIndex(batch, "pos", self.max_level).nodes
        return own.agg(F.count("*").alias("keys"), F.sum(F.col("level") + 1).cast("long").alias("pointers"))

    def trace(self, condition: str) -> DataFrame:
        """Each version of a key with the position of the one before it."""
        return self.nodes.where(condition).select("key", "pos", F.lag("pos").over(W.partitionBy("key").orderBy("pos")).alias("before"))

    def storage(self, key_bytes: int = 16, pointer_bytes: int = 8) -> DataFrame:
        return self.nodes.agg(F.sum(F.lit(key_bytes) + (F.col("level") + 1) * pointer_bytes).cast("long").alias("bytes"))


def full_scan(ledger: DataFrame, condition: str, after: int = 0) -> DataFrame:
    return ledger.where(condition).where(F.col("pos") >= after).select("pos")
