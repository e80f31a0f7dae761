"""Packing token sequences with minimum bin slack.

Documents longer than a window are cut into whole windows and a rest; whole windows stand
alone, rests fill windows together. What rests exist is known from their histogram, which
has one count for each length below the window: the plan is made on it alone. Each step
takes the largest length left, and a bitset subset-sum over the remaining multiset finds
the sum closest to the space left; walking the bitsets back gives how many of each length
it uses. That filling is repeated as often as the counts allow, so the number of steps
follows the number of distinct lengths, not of documents.

A whole window needs no partner: its sequence is numbered where it is cut (task and number
within the task, above all planned sequences), and it moves nowhere. Rests find their place by
their rank among pieces of the same length. Ranks are numbered in shares of about ``share``
pieces of one length, so a length that holds a third of all pieces, or one repeated row, is
no single task at any size; the driver holds one count per share.

A null text is an empty document, which still has its end id; repeated rows and repeated ids are
separate documents; input columns other than id and text are not read; a very long text makes as
many windows as it needs; an empty table gives no rows. Sequence ids are unique, and gapless for
planned sequences only.
"""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.llm.common import lean, stored
from tierbit.llm.tokens import batches_of, crc, encoder


def fill(space: int, counts: dict[int, int]) -> dict[int, int]:
    """A multiset of lengths, within ``counts``, whose sum comes closest to ``space`` from below."""
    mask, reach, steps = (1 << (space + 1)) - 1, 1, []
    for length in sorted((x for x in counts if x <= space and counts[x] > 0), reverse=True):
        left, power = min(counts[length], space // length), 1
        while left and not reach >> space & 1:
            take = min(power, left)
            steps.append((length, take, reach))
            reach |= reach << (length * take) & mask
            left, power = left - take, power * 2
        if reach >> space & 1:
            break
    total, used = reach.bit_length() - 1, {}
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            used[length] = used.get(length, 0) + take
            total -= length * take
    return used


def plan_windows(counts: dict[int, int], window: int) -> list[tuple[int, dict[int, int]]]:
    """(repeats, {length: pieces}) until every counted piece is placed."""
    left, plan = {x: n for x, n in counts.items() if n}, []
    while left:
        first = max(left)
        left[first] -= 1
        used = fill(window - first, left)
        left[first] += 1
        used[first] = used.get(first, 0) + 1
        times = min(left[x] // n for x, n in used.items())
        plan.append((times, used))
        for x, n in used.items():
            left[x] -= n * times
            if not left[x]:
                del left[x]
    return plan


def segments(plan: list[tuple[int, dict[int, int]]]) -> np.ndarray:
    """Rows (length, first rank, pieces per window, first sequence, first offset), by length and rank."""
    rows, used, sequence = [], {}, 0
    for times, pieces in plan:
        offset = 0
        for length, n in sorted(pieces.items(), reverse=True):
            rows.append((length, used.get(length, 0), n, sequence, offset))
            used[length] = used.get(length, 0) + n * times
            offset += length * n
        sequence += times
    return np.array(sorted(rows), dtype=np.int64).reshape(-1, 5)


def cut_pieces(docs: DataFrame, tokenizer: str, end_id: int, window: int = 2048, key: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens (and ids)."""
    tail = struct.pack("<I", end_id)

    def cut(batches):
        task, nth = TaskContext.get().partitionId(), 0
        for batch in batches:
            keys = batch.column("doc_id").to_pylist()
            for run, texts in batches_of(batch.column("text")):
                rows = []
                for i, ids in zip(run, encoder(tokenizer).encode(texts)):
                    ids += tail
                    n = len(ids) // 4
                    for at in range(0, n, window):
                        own = ids[at * 4 : (at + window) * 4]
                        rows.append((keys[i], at, len(own) // 4, crc(own), n, task << 40 | nth, own if with_ids else None))
                        nth += 1
                yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], pa.int64()) for j in range(6)] + [pa.array([r[6] for r in rows], pa.binary())], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "nth", "ids"])

    out = lean(docs).select(F.col(f"`{key}`").cast("long").alias("doc_id"), F.col(f"`{text}`").alias("text")).mapInArrow(cut, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, nth long, ids binary")
    return out if with_ids else out.drop("ids")


def pack(docs: DataFrame, tokenizer: str, end_id: int, window: int = 2048, share: int = 1 << 16, key: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """The pieces with sequence_id and offset."""
    spark = docs.sparkSession
    pieces = stored(cut_pieces(docs, tokenizer, end_id, window, key, text, with_ids), "pieces")
    rests = pieces.where(F.col("length") < window)
    counts = {r[0]: r[1] for r in rests.groupBy("length").count().collect()}
    plan = plan_windows(counts, window)
    seg, planned = segments(plan), sum(t for t, _ in plan)
    shares = {x: -(-n // share) for x, n in counts.items()}
    salted = {x: n for x, n in shares.items() if n > 1}
    salts = F.coalesce(F.create_map(*[F.lit(v) for kv in salted.items() for v in kv])[F.col("length").cast("int")], F.lit(1)) if salted else F.lit(1)
    rests = rests.withColumn("salt", F.pmod(F.xxhash64("doc_id", "start", "nth"), salts).cast("int"))
    first = np.zeros(window + 1, np.int64)  # a length's first share among all
    for x in sorted(shares):
        first[x + 1 :] += shares[x]
    held = np.zeros(int(first[-1]) + 1, np.int64)
    for x, s, n in rests.groupBy("length", "salt").count().collect() if salted else [(x, 0, n) for x, n in counts.items()]:
        held[first[x] + s] = n
    base = np.concatenate([[0], np.cumsum(held)])[:-1]
    for x in sorted(shares, reverse=True):  # ranks start anew with each length
        base[first[x] : first[x] + shares[x]] -= base[first[x]]
    kept = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", *(["ids"] if with_ids else [])]
    shared = spark.sparkContext.broadcast((seg, first, base))  # a row per planned filling, and per share
    ranked = rests.withColumn("rank", F.row_number().over(W.partitionBy("length", "salt").orderBy("doc_id", "start", "ids_crc32", "nth")))

    def place(batches):
        seg, first, base = shared.value
        at = seg[:, 0] * (1 << 48) + seg[:, 1]
        for b in batches:
            length = b.column("length").to_numpy()
            rank = base[first[length] + b.column("salt").to_numpy()] + b.column("rank").to_numpy() - 1
            s = seg[np.searchsorted(at, length * (1 << 48) + rank, "right") - 1]
            turn, within = np.divmod(rank - s[:, 1], s[:, 2])
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in kept], pa.array(s[:, 3] + turn), pa.array(s[:, 4] + within * length)], [*kept, "sequence_id", "offset"])

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, " + "ids binary, " * with_ids + "sequence_id long, offset long"
    whole = pieces.where(F.col("length") == window).select(*kept, (F.col("nth") + planned).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    return ranked.mapInArrow(place, schema).unionByName(whole)


def sequences(pieces: DataFrame, window: int = 2048, pad_id: int = 0) -> DataFrame:
    """sequence_id, n_tokens, ids: each window's bytes, padded; needs ``pack(..., with_ids=True)``."""
    import pandas as pd

    pad = struct.pack("<I", pad_id)

    def join(rows: pd.DataFrame) -> pd.DataFrame:
        ids = b"".join(rows.sort_values("offset")["ids"])
        return pd.DataFrame({"sequence_id": [rows["sequence_id"].iloc[0]], "n_tokens": [len(ids) // 4], "ids": [ids + pad * (window - len(ids) // 4)]})

    return pieces.groupBy("sequence_id").applyInPandas(join, "sequence_id long, n_tokens long, ids binary")
