"""Sharding by a two-pass external shuffle.

Pass one scatters rows uniformly into as many buckets as the table's bytes ask for
(``bucket_bytes`` of text each), by a seeded hash of where a row lies in its input (file and
row number): rows that are alike in every column scatter like any others. Pass two gives
each bucket to one task, which puts it in a canonical order, permutes it by Fisher-Yates and
writes it. Shards are equal runs of the resulting global order, so their row counts differ
by one at most (law ``rows``).

One total per bucket reaches the driver. A retried task writes the same rows in the same
order, because order and random numbers depend on places in the input and on the bucket
only; the same files give the same shards however many tasks read them. A table that isn't
read from files is written first. Null ids and texts are scattered like any others; a very
long text lies whole in its bucket; identical rows are kept, each in a slot of its own; an
empty table gives no rows. Input columns named ``shard`` or ``slot``, in any case, are replaced.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tierbit.llm.common import lean, scratch, stored, without


def fisher_yates(n: int, rng: np.random.Generator) -> np.ndarray:
    """A uniform permutation of 0..n-1: each place, from the last, swaps with one at or before it."""
    order = list(range(n))
    draws = (rng.random(n) * np.arange(1, n + 1)).astype(np.int64).tolist()
    for i in range(n - 1, 0, -1):
        j = draws[i]
        order[i], order[j] = order[j], order[i]
    return np.asarray(order, dtype=np.int64)


def _placed(docs: DataFrame, seed: int) -> DataFrame:
    """(row, mark): every row with a hash of its file's name and its number there."""
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    try:
        return docs.select(row, F.xxhash64(F.lit(seed), F.col("_metadata.file_name"), F.col("_metadata.row_index")).alias("mark"))
    except AnalysisException:  # not read from files
        numbered = stored(docs.select(row, F.monotonically_increasing_id().alias("nth")), "to-shard")
        return numbered.select("row", F.xxhash64(F.lit(seed), "nth").alias("mark"))


def shuffle_into_shards(docs: DataFrame, n_shards: int = 8, seed: int = 17, bucket_bytes: int = 24 << 20, text: str = "text") -> DataFrame:
    """Write ``docs`` as shuffled shards; returns the written files with ``shard`` and ``slot``."""
    spark = docs.sparkSession
    docs = without(docs, "shard", "slot")
    placed = _placed(docs, seed)
    n, size = placed.agg(F.count("*"), F.sum(F.coalesce(F.octet_length(F.col(f"row.`{text}`")), F.lit(0)) + 64)).first()
    buckets = max(1, -(-(size or 0) // bucket_bytes))
    tagged = placed.select("row", "mark", F.pmod(F.xxhash64("mark"), F.lit(buckets)).cast("int").alias("bucket"))
    starts, seen = {}, 0
    for b, rows in sorted((r[0], r[1]) for r in tagged.groupBy("bucket").count().collect()):
        starts[b], seen = seen, seen + rows
    shared = spark.sparkContext.broadcast(starts)
    scattered = tagged.repartitionById(buckets, F.col("bucket"))

    def permute(batches):
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        whole = pa.Table.from_batches(held)
        b = whole["bucket"][0].as_py()  # a task has one bucket
        order = np.argsort(whole["mark"].to_numpy(), kind="stable")[fisher_yates(whole.num_rows, np.random.Generator(np.random.PCG64([seed, b])))]
        pos = shared.value[b] + np.arange(whole.num_rows)
        shard = ((pos + 1) * n_shards - 1) // n
        slot = pos - shard * n // n_shards
        row = whole["row"]
        for at in range(0, len(order), 512):  # texts leave a few at a time
            some = slice(at, at + 512)
            yield pa.RecordBatch.from_arrays([pa.concat_arrays(row.take(pa.array(order[some])).chunks), pa.array(shard[some], pa.int32()), pa.array(slot[some], pa.int64())], ["row", "shard", "slot"])

    schema = T.StructType([T.StructField("row", scattered.schema["row"].dataType), T.StructField("shard", T.IntegerType()), T.StructField("slot", T.LongType())])
    path = scratch(spark, "shards")
    out = lean(scattered).mapInArrow(permute, schema).select("row.*", "shard", "slot")
    out.write.partitionBy("shard").parquet(path)
    return spark.read.schema(out.schema).parquet(path)
