"""Exact dedup by a tree of multiway merges over sorted runs of digests.

Every input partition makes one run: its distinct digests in ascending order, each with its
survivor and its number of rows (made on the map side, so a text that fills a third of the
table leaves one entry per partition). A run is cut by the leading bits of the digest into
segments of about ``segment`` entries, each one row that holds packed sorted arrays. Runs
then meet in rounds: groups of ``fan_in`` neighbouring runs exchange segments of the same
digest range, a task merges them into one sorted segment and only survivors go on, until one
run spans the table. Ranges are halved as runs grow, so a segment stays within the same
bound at every level, whatever the table's size: digests are uniform, and a hot digest
brings one entry of each run to a merge.

A digest is trusted only with its check: SHA-256, byte length and a second hash must all
agree at every level. Texts never move. Results reach the rows by a join on the digest;
groups of more than one row in ``hot`` (there are ``hot`` of those at most) are broadcast,
so no task gets all rows of a hot text.

``keep="largest"`` or ``"smallest"`` names the surviving id; of rows that repeat text and
id one stays. A null text counts as empty; a null id loses against any other; columns other
than id and text, whatever their names, are not read; an empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tierbit.llm.common import drop_rows, flagged, give_back, lean, stored

CHECKED = ["text_sha256", "n_bytes", "check"]
#: An entry: four words of the digest (most significant first), byte length, second hash, survivor's id and row, whether it has an id, rows.
ENTRY = np.dtype([("d0", "<u8"), ("d1", "<u8"), ("d2", "<u8"), ("d3", "<u8"), ("n_bytes", "<i8"), ("check", "<i8"), ("id", "<i8"), ("row", "<i8"), ("has", "?"), ("n", "<i8")])
KEY = ["d0", "d1", "d2", "d3", "n_bytes", "check"]
SEGMENT = "run int, part long, n long, entries binary"


def digests(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, tag (xxhash64 of the text), the checked digest, and a number for every row (its run in the upper bits)."""
    raw = F.encode(F.coalesce(F.col(f"`{text}`"), F.lit("")), "UTF-8")
    return docs.select(F.col(f"`{key}`").cast("long").alias("doc_id"), F.xxhash64(F.col(f"`{text}`")).alias("tag"), raw.alias("raw")).select("doc_id", "tag", F.unhex(F.sha2("raw", 256)).alias("text_sha256"), F.octet_length("raw").cast("long").alias("n_bytes"), F.xxhash64("raw").alias("check"), F.monotonically_increasing_id().alias("row"))


def merge_entries(entries: np.ndarray, largest: bool = True) -> np.ndarray:
    """Sorted distinct entries of several sorted runs laid end to end: survivors by id, then by the earliest row."""
    if not len(entries):
        return entries
    order = np.argsort(entries["d0"], kind="stable")  # detects the runs and merges them
    entries = entries[order]
    if (entries["d0"][1:] == entries["d0"][:-1]).any():  # mostly copies: the other words decide
        entries = entries[np.lexsort([entries[k] for k in reversed(KEY)])]
    fresh = np.ones(len(entries), bool)
    fresh[1:] = np.logical_or.reduce([entries[k][1:] != entries[k][:-1] for k in KEY])
    at = np.flatnonzero(fresh)
    if len(at) == len(entries):
        return entries
    group = np.cumsum(fresh) - 1
    ids = entries["id"] if not largest else ~entries["id"]  # ~x falls as x grows, without overflow
    best = np.lexsort([entries["row"], ids, ~entries["has"], group])
    out = entries[best[at]]
    out["n"] = np.add.reduceat(entries["n"], at)
    return out


def _segments(run: int, bits: int, entries: np.ndarray) -> list[tuple]:
    """A sorted run cut at the ranges of its digests' first ``bits`` bits."""
    part = entries["d0"] >> np.uint64(64 - bits) if bits else np.zeros(len(entries), np.uint64)
    at = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]])) if len(part) else np.zeros(0, int)
    ends = [*at[1:], len(entries)]
    return [(run, int(part[i]), int(j - i), entries[i:j].tobytes()) for i, j in zip(at, ends)]


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.int64(), pa.int64(), pa.binary()))], ["run", "part", "n", "entries"])


def _bits(entries: int, segment: int) -> int:
    return min(40, max(0, math.ceil(math.log2(max(1, entries) / segment))))


def sorted_runs(rows: DataFrame, largest: bool, segment: int, longest: int) -> DataFrame:
    """Each input partition as one sorted run in segments; nothing moves."""
    bits = _bits(longest, segment)

    def make(batches):
        give_back()
        held, parts = {}, 0  # sorted pieces of the run, of all batches that came as one

        def flush():
            for run, pieces in held.items():
                out = _segments(run, bits, merge_entries(np.concatenate(pieces), largest))
                for i in range(0, len(out), 16):
                    yield _rows(out[i : i + 16])
            held.clear()

        for b in batches:
            if not b.num_rows:
                continue
            e = np.zeros(b.num_rows, ENTRY)
            words = np.frombuffer(b"".join(b.column("text_sha256").to_pylist()), ">u8").reshape(-1, 4)
            for j in range(4):
                e[f"d{j}"] = words[:, j]
            for c in ("n_bytes", "check", "row"):
                e[c] = b.column(c).to_numpy()
            e["has"] = b.column("doc_id").is_valid().to_numpy(zero_copy_only=False)
            e["id"] = b.column("doc_id").fill_null(0).to_numpy()
            e["n"] = 1
            runs = (e["row"] >> 33).astype(np.int64)
            for run in np.unique(runs).tolist():
                held.setdefault(run, []).append(merge_entries(e[runs == run], largest))
            parts += b.num_rows
            if parts >= 4 << 20:  # a very long partition gives several runs under one number
                yield from flush()
                parts = 0
        yield from flush()

    return lean(rows).select("doc_id", *CHECKED, "row").mapInArrow(make, SEGMENT)


def merge_runs(rows: DataFrame, keep: str = "largest", fan_in: int = 16, segment: int = 1 << 15) -> DataFrame:
    """One row per distinct text: the checked digest, keep_id, keep_row and group_size."""
    largest = keep == "largest"
    by_run = rows.groupBy(F.shiftright("row", 33).cast("int").alias("run")).count()
    n_runs, longest = by_run.agg(F.max("run"), F.max("count")).first()
    runs, width = (n_runs or 0) + 1, longest or 1
    level = sorted_runs(rows, largest, segment, width)
    for _ in range(max(1, math.ceil(math.log(max(runs, 2), fan_in)))):
        before, width = _bits(width, segment), width * fan_in
        after = _bits(width, segment)
        tasks = max(1, min(1 << after, 1 << 16) * -(-runs // fan_in) // 8)
        runs = -(-runs // fan_in)
        level = _merged(level, largest, fan_in, before, after, tasks)
    return _unpacked(level)


def _merged(level: DataFrame, largest: bool, fan_in: int, before: int, after: int, tasks: int) -> DataFrame:
    def cut(batches):
        for b in batches:
            out = []
            for run, raw in zip(b.column("run").to_pylist(), b.column("entries").to_pylist()):
                out += _segments(run // fan_in, after, np.frombuffer(raw, ENTRY))
            for i in range(0, len(out), 16):
                yield _rows(out[i : i + 16])

    def merge(batches):
        give_back()
        at, held = None, []

        def done():
            entries = merge_entries(np.concatenate(held), largest)
            return _rows([(*at, len(entries), entries.tobytes())])

        for b in batches:  # sorted: the segments of one place come one after another
            for run, part, raw in zip(b.column("run").to_pylist(), b.column("part").to_pylist(), b.column("entries").to_pylist()):
                if (run, part) != at:
                    if held:
                        yield done()
                    at, held = (run, part), []
                held.append(np.frombuffer(raw, ENTRY))
        if held:
            yield done()

    cut_up = lean(level).mapInArrow(cut, SEGMENT)
    return lean(cut_up.repartition(tasks, "run", "part").sortWithinPartitions("run", "part")).mapInArrow(merge, SEGMENT)


def _unpacked(level: DataFrame) -> DataFrame:
    def read(batches):
        for b in batches:
            for raw in b.column("entries").to_pylist():
                e = np.frombuffer(raw, ENTRY)
                words = np.stack([e[f"d{j}"] for j in range(4)], 1).astype(">u8").tobytes()
                ids = pa.array(np.ascontiguousarray(e["id"]), mask=~e["has"])
                yield pa.RecordBatch.from_arrays([pa.array([words[32 * i : 32 * i + 32] for i in range(len(e))], pa.binary()), *[pa.array(np.ascontiguousarray(e[c])) for c in ("n_bytes", "check")], ids, *[pa.array(np.ascontiguousarray(e[c])) for c in ("row", "n")]], [*CHECKED, "keep_id", "keep_row", "group_size"])

    return level.mapInArrow(read, "text_sha256 binary, n_bytes long, check long, keep_id long, keep_row long, group_size long")


def exact_dedup(docs: DataFrame, keep: str = "largest", fan_in: int = 16, key: str = "doc_id", text: str = "text", hot: int = 10_000) -> DataFrame:
    """doc_id, tag (xxhash64 of the text), keep_id, group_size, kept, text_sha256 for every row."""
    rows = stored(digests(docs, key, text), "digests")
    groups = stored(merge_runs(rows, keep, fan_in), "groups")
    bar = max(1, rows.count() // hot)  # fewer than ``hot`` groups hold more rows
    large = F.broadcast(groups.where(F.col("group_size") > bar).withColumn("large", F.lit(True)))
    marked = rows.join(large, CHECKED, "left")
    rest = marked.where("large is null").select(*rows.columns).join(groups.where(F.col("group_size") <= bar), CHECKED)
    both = marked.where("large").select(*rest.columns).unionByName(rest)
    return both.select("doc_id", "tag", "keep_id", "group_size", (F.col("row") == F.col("keep_row")).alias("kept"), F.lower(F.hex("text_sha256")).alias("text_sha256"))


def survivors(docs: DataFrame, keep: str = "largest", key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with one row of each text. Rows that repeat id and text are told apart by nothing but their other columns: the greatest stays."""
    named = F.coalesce(F.col("doc_id"), F.lit(-1).cast("long")).alias("doc_id")
    marks = exact_dedup(docs, keep, key=key, text=text).groupBy(named, "tag").agg(F.max("kept").alias("stays"), F.count("*").alias("n"))
    marks = stored(marks.where("not stays or n > 1"), "marks")
    rest = drop_rows(docs, marks.where("not stays"), key, text)
    wrapped = rest.select(F.struct(*[F.col(f"`{c}`") for c in rest.columns]).alias("row"), F.coalesce(F.col(f"`{key}`").cast("long"), F.lit(-1).cast("long")).alias("doc_id"), F.xxhash64(F.col(f"`{text}`")).alias("tag"))
    marked = flagged(wrapped, marks.where("stays"), ["doc_id", "tag"])
    maybe = marked.where("maybe").join(marks.where("stays").select("doc_id", "tag", F.lit(True).alias("again")), ["doc_id", "tag"], "left").select("row", "doc_id", "tag", "again")
    once = maybe.where("again").groupBy("doc_id", "tag", F.col(f"row.`{text}`").alias("_text")).agg(F.max(F.struct(F.col(f"row.`{key}`").alias("i"), "row")).getField("row").alias("row"))
    return marked.where("not maybe").select("row").unionByName(maybe.where("again is null").select("row")).unionByName(once.select("row")).select("row.*")
