"""The ledger as a stream: appending to the index, open-tree state, windows of hits."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tierbit.config import IndexSpec
from tierbit.sources.ledger import extract
from tierbit.sources.storage import scratch
from tierbit.sources.store import Keeper


def split_files(df: DataFrame, n: int, order: str = "pos") -> str:
    """Write a table as ``n`` files, in order and one after another, for a file stream; returns the folder."""
    path = scratch(df.sparkSession, "stream")
    low, high = df.agg(F.min(order), F.max(order)).first()
    width = max(1, -(-(int(high or 0) - int(low or 0) + 1) // n))
    for i in range(n):
        df.where(F.expr(f"({order} - {int(low or 0)}) div {width} = {i}")).coalesce(1).sortWithinPartitions(order).write.mode("append").parquet(path)
    return path


def source(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def timed(stream: DataFrame, col: str = "ts", lateness: str = "1 day") -> DataFrame:
    """Event time for windows: watermarks need a timestamp with a zone."""
    return stream.withColumn(col, F.col(col).cast("timestamp")).withWatermark(col, lateness)


def finish(df: DataFrame, name: str, mode: str) -> DataFrame:
    """Run a stream over what is there, into a memory table."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", scratch(df.sparkSession, "offsets")).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def index_stream(spark: SparkSession, path: str, schema, dims: dict[str, str], spec: IndexSpec) -> DataFrame:
    """The index from a stream of record files in order of position: a batch appends to the kept index, which
    touches its open tree only. What the manifest counts already is left out, so a replayed batch changes nothing."""
    keeper = Keeper(spark, scratch(spark, "streamed"), spec)

    def take(batch: DataFrame, _: int) -> None:
        done = keeper.manifest.n_records
        last = batch.agg(F.max("pos")).first()[0]
        if last is not None and last >= done:
            keeper.append(extract(batch.where(F.col("pos") >= done), dims), last + 1 - done, flush=True)

    q = source(spark, path, schema).writeStream.foreachBatch(take).trigger(availableNow=True).option("checkpointLocation", scratch(spark, "offsets")).start()
    q.awaitTermination()
    return keeper.index()


def open_tree_state(stream: DataFrame, b: int) -> DataFrame:
    """(key, node, mask): leaf masks from a stream of (key, pos); a node's mask leaves its state once a later node begins."""

    def step(key: tuple, batches, state: GroupState):
        node, mask = state.get if state.exists else (-1, 0)
        out = []
        for pdf in batches:
            for pos in sorted(pdf["pos"]):
                if pos // b != node:
                    if node >= 0:
                        out.append((key[0], node, mask))
                    node, mask = int(pos // b), 0
                mask |= 1 << (b - 1 - int(pos % b))
        state.update((node, mask))
        yield pd.DataFrame(out, columns=["key", "node", "mask"])

    return stream.groupBy("key").applyInPandasWithState(step, "key string, node long, mask long", "node long, mask long", "append", GroupStateTimeout.NoTimeout)
