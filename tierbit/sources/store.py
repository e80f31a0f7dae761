"""Keeping an index in files: immutable segments of full trees, an open tail, versioned manifests."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tierbit.config import IndexSpec
from tierbit.operators.build import keyed, merge
from tierbit.sources.storage import shuffles_removed, stored

SCHEMA = "level int, dim string, key string, tree long, node long, mask long"


@dataclass
class Manifest:
    version: int = 0
    n_records: int = 0
    open_tree: int = 0
    segments: list[str] = field(default_factory=list)
    tail: str | None = None


class Keeper:
    """Appends batches below ``path``.

    When the last record of a tree arrives its masks are written once, in a segment laid
    out by level and sorted by feature; the open tree is a tail segment that the next version
    replaces, merged by OR where a mask was cut in two. A version is one small text file
    written last: readers of an older one still find all its files, and a batch that is
    replayed after a failure leaves the same masks.
    """

    def __init__(self, spark: SparkSession, path: str, spec: IndexSpec):
        self.spark, self.path, self.spec = spark, path.rstrip("/"), spec
        self.pending: DataFrame | None = None
        self.manifest = self._load()

    def _load(self) -> Manifest:
        try:
            rows = self.spark.read.text(f"{self.path}/manifest").collect()
        except Exception as e:  # no version yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return Manifest()
        return max((Manifest(**json.loads(r[0])) for r in rows), key=lambda m: m.version)

    def _read(self, names: list[str]) -> DataFrame:
        if not names:
            return self.spark.createDataFrame([], SCHEMA)
        return self.spark.read.schema(SCHEMA + ", part string").option("basePath", f"{self.path}/masks").parquet(*[f"{self.path}/masks/part={n}" for n in names]).select("level", "dim", "key", "tree", "node", "mask")

    def index(self) -> DataFrame:
        """Full trees and the tail; both in the layout of a built index."""
        return self._read([*self.manifest.segments, *([self.manifest.tail] if self.manifest.tail else [])])

    def append(self, features: DataFrame, n_new: int, flush: bool = False) -> Manifest:
        """Take records ``n_records .. n_records + n_new - 1``. Without ``flush`` only full trees are written; their records' rest waits."""
        m = self.manifest
        if not flush:  # it may wait long: read what it comes from only once
            features = stored(features, "waiting")
        self.pending = features if self.pending is None else self.pending.unionByName(features)
        self.waiting = getattr(self, "waiting", 0) + n_new
        end = m.n_records + self.waiting
        if end // self.spec.tree == m.open_tree and not flush:
            return m
        version, tree = m.version + 1, end // self.spec.tree
        fresh = keyed(self.pending, self.spec)
        whole = merge(self._read([m.tail]), fresh) if m.tail and m.n_records % self.spec.tree else fresh  # else the tail is empty
        segments = list(m.segments)
        if tree > m.open_tree:
            name = f"segment-{version:06d}"
            self._write(whole.where(F.col("tree") < tree), name)
            segments.append(name)
        name = f"tail-{version:06d}"
        self._write(whole.where(F.col("tree") >= tree), name)
        new = Manifest(version, end, tree, segments, name)
        self.spark.createDataFrame([(json.dumps(asdict(new)),)], "value string").coalesce(1).write.mode("append").text(f"{self.path}/manifest")
        self.manifest, self.pending, self.waiting = new, None, 0
        return new

    def _write(self, masks: DataFrame, name: str) -> None:
        with shuffles_removed(self.spark):
            masks.repartition("dim", "key", "tree").sortWithinPartitions("dim", "key", "tree", "node").write.partitionBy("level").mode("overwrite").parquet(f"{self.path}/masks/part={name}")
