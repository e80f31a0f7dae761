"""A Python data source over packed index rows: filters on feature and tree reach the reader."""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThanOrEqual, InputPartition

SCHEMA = "dim string, key string, tree long, root long, middles array<bigint>, leaves array<bigint>"


class PackedReader(DataSourceReader):
    def __init__(self, options):
        self.files = json.loads(options["files"])
        self.equal = {c: options[c] for c in ("dim", "key") if options.get(c)}
        self.least = {"tree": int(options["from_tree"])} if options.get("from_tree") else {}

    def partitions(self):
        return [InputPartition(f) for f in self.files] or [InputPartition(None)]

    def read(self, partition):
        if partition.value is None:
            return
        import pyarrow.parquet as pq
        from pyarrow.fs import FileSystem

        fs, path = FileSystem.from_uri(partition.value)
        filters = [(c, "=", v) for c, v in self.equal.items()] + [("tree", ">=", v) for v in self.least.values()]
        yield from pq.read_table(path, filesystem=fs, filters=filters or None, columns=["dim", "key", "tree", "root", "middles", "leaves"]).to_batches()


class PushingReader(PackedReader):
    """Takes filters from the plan; Spark allows it where its filter pushdown for Python sources is on."""

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute in (("dim",), ("key",)):
                self.equal[f.attribute[0]] = f.value
            elif isinstance(f, GreaterThanOrEqual) and f.attribute == ("tree",):
                self.least["tree"] = f.value
            else:
                yield f


class PackedSource(DataSource):
    """Options: ``files``, a JSON list of Parquet files; ``dim``, ``key``, ``from_tree`` to read less; ``push`` to take the plan's filters."""

    @classmethod
    def name(cls):
        return "packed_index"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return (PushingReader if self.options.get("push") == "true" else PackedReader)(self.options)
