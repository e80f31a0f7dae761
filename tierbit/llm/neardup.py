"""Near-duplicate groups by dart-throwing weighted MinHash and banded joining.

A document is a weighted set of five-word shingles (lower case, words split at white
space; a text of fewer words is one shingle). Where ``measure`` is the Jaccard of sets every
shingle weighs 1, else one seen c times weighs 1 + ln c: search and decision agree. Each
weight is a region of unit-wide strips, and every strip receives darts at unit rate over
time from a generator seeded by the strip alone, so equal regions of two documents get
equal darts. Darts above the weight miss. A dart's hash names one of the signature's
coordinates, and each coordinate keeps its earliest dart: the work follows the number of
shingles plus that of darts, not their product. Bands of coordinates are joined.

No step holds a group whole: copies of one normalised text are one class first; within a
band's bucket each class is tried against the bucket's smallest, against the one that meets
the most others over all bands, and against a neighbour in the order of the following band
(in salted shares of large buckets), so these candidates grow with documents times bands.
Most buckets are joined into one group by them, and their other pairs can't change it. In
the rest every pair of classes not yet joined is compared as well (``remainder``), so groups
are those of all pairs that share a bucket: classes of a bucket are dealt into blocks of
bounded size, a task gets two blocks, compares signatures as matrices and checks exactly what
agrees, and only links leave it. No pair is written, but comparisons still grow with the
square of a bucket whose classes don't join. Candidates whose signatures agree enough are
checked exactly (``measure``: Jaccard of the shingle sets, or of the weights), and groups are
the connected components of what passes.

Result for every row: cluster_id (least doc_id of the group), cluster_size (rows), links
(links found between its class and others; pairs of a
group that is joined already aren't all tried), kept (true for the row with the least id of each
group; rows that repeat that id and text share its fate). A null text counts as empty;
empty texts are copies of each other; a null id counts as -1. Columns other than id and text,
whatever their names, are not read; texts are read whole. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.llm.common import flagged, give_back, lean, stored

WORDS = 5
_P = np.uint64(0x100000001B3)
_POWERS: list[np.ndarray] = []


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit integers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS[0]) < n:
        inverse = np.uint64(pow(int(_P), -1, 1 << 64))
        _POWERS[:] = [np.cumprod(np.concatenate([[np.uint64(1)], np.full(max(n, 1 << 16) - 1, p)]).astype(np.uint64), dtype=np.uint64) for p in (_P, inverse)]
    return _POWERS[0], _POWERS[1]


def normalised(text: str | None) -> str:
    return " ".join((text or "").lower().split())


def shingles(norm: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes, ascending, and how often each occurs."""
    raw = np.frombuffer(norm.encode("utf-8", "replace"), np.uint8)
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    up, down = _powers(len(raw) + 1)
    sums = np.concatenate([[np.uint64(0)], np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], dtype=np.uint64)])
    gaps = np.flatnonzero(raw == 32)
    starts, ends = np.concatenate([[0], gaps + 1]), np.concatenate([gaps, [len(raw)]])
    words = mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))
    n = max(1, len(words) - WORDS + 1)
    h = np.zeros(n, np.uint64)
    for j in range(min(WORDS, len(words))):
        h = h * np.uint64(0x9E3779B97F4A7C15) + words[j : j + n]
    return np.unique(mix(h), return_counts=True)


def weights_of(counts: np.ndarray, measure: str = "weights") -> np.ndarray:
    return np.ones(len(counts)) if measure == "set" else 1.0 + np.log(counts)


def dart_signatures(sets: list[tuple[np.ndarray, np.ndarray]], size: int, seed: int = 1, wide: float = 1.0) -> np.ndarray:
    """For each (items, weights) and coordinate the identity (64-bit) of the earliest dart; zeros for an empty set.

    ``wide`` scales the time window; sets left with an empty coordinate are thrown again with twice the window.
    """
    out = np.zeros((len(sets), size), np.uint64)
    full = [i for i, (items, _) in enumerate(sets) if len(items)]
    if not full:
        return out
    items, weights = (np.concatenate([sets[i][k] for i in full]) for k in (0, 1))
    sizes = np.array([len(sets[i][0]) for i in full])
    set_of = np.repeat(np.arange(len(full)), sizes)
    windows = wide * (size * np.log(size) + 2 * size) / np.bincount(set_of, weights)
    strips = np.ceil(weights).astype(np.int64)
    owner = np.repeat(np.arange(len(items)), strips)
    level = np.arange(len(owner)) - np.repeat(np.cumsum(strips) - strips, strips)
    key = mix(items[owner] + mix(level.astype(np.uint64) + np.uint64(seed << 20)))
    height = np.minimum(weights[owner] - level, 1.0)
    whose = set_of[owner]
    window, t = windows[whose], np.zeros(len(key))
    found = []
    while len(key):
        u = mix(key + np.uint64(0xD1B54A32D192ED03))
        t = t - np.log1p(-((u >> np.uint64(11)).astype(np.float64) * 2.0**-53))
        on = t < window
        key, t, u, height, whose, window = key[on], t[on], u[on], height[on], whose[on], window[on]
        dart = mix(u ^ np.uint64(0xA0761D6478BD642F))
        hit = (dart >> np.uint64(40)).astype(np.float64) * 2.0**-24 < height
        found.append((t[hit], dart[hit], (whose * size + (mix(dart) % np.uint64(size)).astype(np.int64))[hit]))
        key = u  # the strip's next dart follows from this one
    t, dart, at = (np.concatenate([f[k] for f in found]) for k in range(3))
    order = np.argsort(-t, kind="stable")
    flat, seen = np.zeros(len(full) * size, np.uint64), np.zeros(len(full) * size, bool)
    flat[at[order]] = dart[order]  # the earliest is written last
    seen[at] = True
    whole = seen.reshape(-1, size).all(axis=1)
    for i, row, done in zip(full, flat.reshape(-1, size), whole):
        out[i] = row
    again = [i for i, done in zip(full, whole) if not done]
    if again:
        out[again] = dart_signatures([sets[i] for i in again], size, seed, wide * 2)
    return out


def dart_signature(items: np.ndarray, weights: np.ndarray, size: int, seed: int = 1) -> np.ndarray:
    return dart_signatures([(items, weights)], size, seed)[0]


def band_keys(signature: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One 64-bit key per band, over the band's number and coordinates."""
    h = np.arange(1, bands + 1, dtype=np.uint64)
    for j in range(rows):
        h = mix(h * np.uint64(0x9E3779B97F4A7C15) + signature.reshape(bands, rows)[:, j])
    return h.view(np.int64)


def signed(docs: DataFrame, bands: int, rows: int, key: str, text: str, measure: str = "set") -> DataFrame:
    """doc_id, tag (of the text as it is), class (of the normalised text), bands, a byte of each coordinate, and mass (of the shingles under ``measure``)."""

    def make(batches):
        give_back()
        for b in batches:
            ids, tags, texts = b.column("doc_id"), b.column("tag"), b.column("text")
            for at in range(0, len(texts), 128):
                cls, sets, mass = [], [], []
                for t in texts.slice(at, 128):
                    norm = normalised(t.as_py())
                    items, counts = shingles(norm)
                    sets.append((items, weights_of(counts, measure)))
                    mass.append(float(sets[-1][1].sum()))
                    cls.append(hashlib.md5(norm.encode("utf-8", "replace")).digest())
                made = dart_signatures(sets, bands * rows)
                keys = [band_keys(s, bands, rows) if len(x[0]) else [] for s, x in zip(made, sets)]
                sig = [s.tobytes() for s in made.astype(np.uint8)]
                yield pa.RecordBatch.from_arrays([ids.slice(at, 128), tags.slice(at, 128), pa.array(cls, pa.binary()), pa.array(keys, pa.list_(pa.int64())), pa.array(sig, pa.binary()), pa.array(mass, pa.float64())], ["doc_id", "tag", "class", "bands", "sig", "mass"])

    return lean(docs).select(F.coalesce(F.col(f"`{key}`").cast("long"), F.lit(-1).cast("long")).alias("doc_id"), F.xxhash64(F.col(f"`{text}`")).alias("tag"), F.col(f"`{text}`").alias("text")).mapInArrow(make, "doc_id long, tag long, class binary, bands array<long>, sig binary, mass double")


def candidates(entries: DataFrame, share: int = 4096, near: int = 1) -> DataFrame:
    """Pairs a < b of classes: each bucket's classes with its least, its most met, and ``near`` neighbours.

    ``entries`` hold class, band and, if given, ``after``: the class's key in the following band. Most
    met is the class that shares the most buckets with others, which is the original among
    edited copies that are less like each other. Neighbours are taken in the order of
    ``after``, so classes that agree in a second band stand side by side; a bucket of up to
    ``near`` + 1 classes is tried whole.
    """
    buckets = stored(entries.groupBy("band").agg(F.count("*").alias("n"), F.min("class").alias("head")).where("n > 1"), "buckets")
    inside = stored(entries.join(buckets, "band"), "inside")
    met = inside.groupBy("class").agg(F.sum("n").alias("met"))
    central = inside.select("class", "band").join(met, "class").groupBy("band").agg(F.min(F.struct(-F.col("met"), "class")).getField("class").alias("centre"))
    placed = inside.join(central, "band").withColumn("place", F.xxhash64("class", "band")).withColumn("salt", F.pmod("place", F.ceil(F.col("n") / share)))
    order = [c for c in ("after", "place") if c in placed.columns]
    beside = W.partitionBy("band", "salt").orderBy(*order)
    both = placed.select("class", "head", "centre", *[F.lag("class", i + 1).over(beside).alias(f"n{i}") for i in range(near)]).select("class", F.explode(F.array_distinct(F.array("head", "centre", *[f"n{i}" for i in range(near)]))).alias("other"))
    return both.where("other is not null and other <> class").select(F.least("class", "other").alias("a"), F.greatest("class", "other").alias("b")).distinct()


PLACED = "band long, i int, j int, class binary, root binary, mass double, block int, sig binary, bands array<long>"


def _groups(batches, by: int):
    """Rows of each group of the first ``by`` columns, from sorted batches."""
    give_back()
    at, held = None, []
    for b in batches:
        for row in zip(*[c.to_pylist() for c in b.columns]):
            if row[:by] != at:
                if held:
                    yield held
                at, held = row[:by], []
            held.append(row)
    if held:
        yield held


def close_pairs(rows: list[tuple], size: int, threshold: float):
    """(x, y) places in ``rows`` (as PLACED) of the pairs of the group's two blocks whose roots differ, whose masses
    and signatures allow the threshold, and whose first common band is the group's."""
    band, i, j = rows[0][:3]
    sig = np.frombuffer(b"".join(r[7] for r in rows), np.uint8).reshape(-1, size)
    keys, mass, block = np.array([r[8] for r in rows], np.int64), np.array([r[5] for r in rows]), np.array([r[6] for r in rows])
    names: dict[bytes, int] = {}
    root = np.array([names.setdefault(r[4], len(names)) for r in rows])
    left, right = np.flatnonzero(block == i), np.flatnonzero(block == j)
    least = agreement(threshold, size)
    for at in range(0, len(left), 32):
        x = left[at : at + 32]
        ok = (root[x][:, None] != root[right]) & (np.minimum(mass[x][:, None], mass[right]) >= np.maximum(mass[x][:, None], mass[right]) * (threshold - 1e-9))
        if i == j:
            ok &= x[:, None] < right
        p, q = np.nonzero(ok)
        p, q = x[p], right[q]
        for some in range(0, len(p), 1 << 15):
            a, b = p[some : some + (1 << 15)], q[some : some + (1 << 15)]
            on = (sig[a] == sig[b]).mean(axis=1) >= least
            a, b = a[on], b[on]
            first = (keys[a] == keys[b]).argmax(axis=1)
            on = keys[a, first] == band
            yield from zip(a[on].tolist(), b[on].tolist())


def agreement(threshold: float, size: int) -> float:
    """The share of equal coordinates, five standard errors below the threshold: loses 1 pair in a million."""
    return threshold - 5 * (threshold * (1 - threshold) / size) ** 0.5


def remainder(entries: DataFrame, roots: DataFrame, sigs: DataFrame, size: int, threshold: float, block: int = 256, block_mass: int = 1 << 18) -> DataFrame:
    """The rows (as PLACED) of all classes that have a close pair in a bucket of several ``roots``, once for each pair of blocks.

    ``entries`` hold class, band and mass, ``sigs`` class, sig and bands. A bucket's classes are dealt
    into blocks of about ``block`` classes and ``block_mass`` shingles, and each pair of blocks meets in one group.
    """
    rooted = stored(entries.select("class", "band", "mass").join(roots, "class", "left").withColumn("root", F.coalesce("root", "class")), "rooted")
    split = rooted.groupBy("band").agg(F.count("*").alias("n"), F.sum("mass").alias("all_mass"), F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high")
    split = split.select("band", F.greatest(F.ceil(F.col("n") / block), F.ceil(F.col("all_mass") / block_mass)).cast("int").alias("blocks"))
    members = rooted.join(split, "band").withColumn("block", F.pmod(F.xxhash64("class", F.lit(5)), F.col("blocks")).cast("int"))
    dealt = stored(members.select("band", "class", "root", "mass", "block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")), "members")
    placed = dealt.join(sigs, "class").select("band", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "class", "root", "mass", "block", "sig", "bands")

    def find(batches):
        for rows in _groups(batches, 3):
            used = sorted({p for pair in close_pairs(rows, size, threshold) for p in pair})
            for at in range(0, len(used), 256):
                yield placed_batch([rows[p] for p in used[at : at + 256]])

    return stored(lean(placed.repartition("band", "i", "j").sortWithinPartitions("band", "i", "j")).mapInArrow(find, PLACED), "open")


def placed_batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.float64(), pa.int32(), pa.binary(), pa.list_(pa.int64()))
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], [c.split()[0] for c in PLACED.split(", ")])


def remainder_links(found: DataFrame, sets: DataFrame, size: int, threshold: float, measure: str) -> DataFrame:
    """Links (a, b) among the rows of ``remainder``, by the exact shingle sets (class, items, counts)."""
    both = found.join(sets, "class").select(*[c.split()[0] for c in PLACED.split(", ")], "items", "counts")

    def check(batches):
        for rows in _groups(batches, 3):
            made = [(np.frombuffer(r[9], np.uint64), np.frombuffer(r[10], np.int64)) for r in rows]
            out = [(min(rows[x][3], rows[y][3]), max(rows[x][3], rows[y][3])) for x, y in close_pairs(rows, size, threshold) if jaccard(*made[x], *made[y], measure) >= threshold]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([o[k] for o in out], pa.binary()) for k in (0, 1)], ["a", "b"])

    return lean(both.repartition("band", "i", "j").sortWithinPartitions("band", "i", "j")).mapInArrow(check, "a binary, b binary")


def shingle_sets(texts: DataFrame) -> DataFrame:
    """(class, items, counts) of (class, text)."""

    def make(batches):
        give_back()
        for b in batches:
            for at in range(0, b.num_rows, 128):
                some = [shingles(normalised(t.as_py())) for t in b.column("text").slice(at, 128)]
                yield pa.RecordBatch.from_arrays([b.column("class").slice(at, 128), *[pa.array([s[k].tobytes() for s in some], pa.binary()) for k in (0, 1)]], ["class", "items", "counts"])

    return lean(texts.select("class", "text")).mapInArrow(make, "class binary, items binary, counts binary")


def similar(pairs: DataFrame, texts: DataFrame, threshold: float, measure: str) -> DataFrame:
    """The pairs whose exact similarity reaches the threshold."""
    both = pairs.join(texts.select(F.col("class").alias("a"), F.col("text").alias("text_a")), "a").join(texts.select(F.col("class").alias("b"), F.col("text").alias("text_b")), "b")

    def check(batches):
        seen: dict[bytes, tuple] = {}

        def get(key, text):
            if key not in seen:
                if len(seen) > 2000:
                    seen.clear()
                seen[key] = shingles(normalised(text))
            return seen[key]

        for b in batches:
            a_, b_ = b.column("a").to_pylist(), b.column("b").to_pylist()
            kept = []
            for i, (x, y, tx, ty) in enumerate(zip(a_, b_, b.column("text_a").to_pylist(), b.column("text_b").to_pylist())):
                (p, n), (q, m) = get(x, tx), get(y, ty)
                if jaccard(p, n, q, m, measure) >= threshold:
                    kept.append(i)
            yield pa.RecordBatch.from_arrays([pa.array([a_[i] for i in kept], pa.binary()), pa.array([b_[i] for i in kept], pa.binary())], ["a", "b"])

    return both.select("a", "b", "text_a", "text_b").mapInArrow(check, "a binary, b binary")


def jaccard(p: np.ndarray, n: np.ndarray, q: np.ndarray, m: np.ndarray, measure: str = "set") -> float:
    common, i, j = np.intersect1d(p, q, assume_unique=True, return_indices=True)
    if measure == "set":
        return len(common) / max(1, len(p) + len(q) - len(common))
    inside = float(np.minimum(weights_of(n[i]), weights_of(m[j])).sum())
    return inside / max(1e-12, float(weights_of(n).sum() + weights_of(m).sum()) - inside)


def components(links: DataFrame, rounds: int = 40) -> DataFrame:
    """class, root: alternating rounds that hang neighbours on the least one, until nothing moves."""
    edges, before = stored(links.select(F.col("a").alias("u"), F.col("b").alias("v")), "links"), None
    state = lambda e: e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    for _ in range(rounds):
        both = edges.union(edges.select("v", "u"))
        least = stored(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "least")
        up = both.join(least, "u").where("v > u and v <> m").select(F.col("m").alias("u"), "v").distinct()
        up = stored(up, "large")  # every larger neighbour now hangs on the least
        least = stored(up.groupBy("v").agg(F.min("u").alias("m")), "least")
        hung = up.join(least, "v")
        edges = stored(hung.select(F.col("m").alias("u"), "v").union(hung.where("u <> m").select(F.col("m").alias("u"), F.col("u").alias("v"))).distinct(), "small")
        now = state(edges)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("v").alias("class"), F.col("u").alias("root"))


def near_duplicates(docs: DataFrame, threshold: float = 0.8, bands: int = 24, rows: int = 5, measure: str = "set", key: str = "doc_id", text: str = "text", near: int = 1, block: int = 256) -> DataFrame:
    """doc_id, tag (xxhash64 of the text), cluster_id, cluster_size, links, kept for every row."""
    size = bands * rows
    all_rows = stored(signed(docs, bands, rows, key, text, measure), "signed")
    classes = stored(all_rows.groupBy("class").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("n")), "classes")
    beside = F.expr("transform(bands, (x, i) -> named_struct('band', x, 'after', bands[(i + 1) % size(bands)]))")
    entries = all_rows.select("class", "bands", "mass").dropDuplicates(["class"]).select("class", "mass", F.inline(beside))
    entries = stored(entries, "entries")
    pairs = stored(candidates(entries.drop("mass"), near=near), "pairs")
    sigs = all_rows.join(classes.select("class", F.col("first_id").alias("doc_id")), ["class", "doc_id"], "left_semi").groupBy("class").agg(F.min("sig").alias("sig"), F.min("bands").alias("bands"))

    def agree(batches):
        for b in batches:
            x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint8).reshape(-1, size) for c in ("sig_a", "sig_b"))
            yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b")], ["a", "b"]).filter(pa.array((x == y).mean(axis=1) >= agreement(threshold, size)))

    sigs = stored(sigs, "sigs")

    def name(batches):
        for b in batches:
            cls = [hashlib.md5(normalised(t.as_py()).encode("utf-8", "replace")).digest() for t in b.column("text")]
            yield pa.RecordBatch.from_arrays([pa.array(cls, pa.binary()), b.column("doc_id"), b.column("text")], ["class", "doc_id", "text"])

    def texts_of(some):
        """(class, text) of the classes in ``some``."""
        needed = stored(some.distinct().join(classes, "class").select("class", F.col("first_id").alias("doc_id")), "needed")
        rows = flagged(docs.select(F.coalesce(F.col(f"`{key}`").cast("long"), F.lit(-1).cast("long")).alias("doc_id"), F.col(f"`{text}`").alias("text")), needed, ["doc_id"]).where("maybe").drop("maybe")
        return rows.mapInArrow(name, "class binary, doc_id long, text string").join(needed, ["class", "doc_id"], "left_semi").groupBy("class").agg(F.min("text").alias("text"))

    close = pairs.join(sigs.select(F.col("class").alias("a"), F.col("sig").alias("sig_a")), "a").join(sigs.select(F.col("class").alias("b"), F.col("sig").alias("sig_b")), "b").select("a", "b", "sig_a", "sig_b").mapInArrow(agree, "a binary, b binary")
    close = stored(close, "close")
    texts = stored(texts_of(close.select(F.col("a").alias("class")).union(close.select("b"))), "texts")
    links = stored(similar(close, texts, threshold, measure), "similar")
    found = remainder(entries, components(links), sigs, size, threshold, block)
    sets = stored(shingle_sets(texts_of(found.select("class"))), "sets")
    rest = remainder_links(found, sets, size, threshold, measure)
    links = stored(links.unionByName(rest).distinct(), "all_links")
    roots = components(links)
    degree = links.select(F.explode(F.array("a", "b")).alias("class")).groupBy("class").agg(F.count("*").alias("links"))
    placed = classes.join(roots, "class", "left").join(degree, "class", "left").withColumn("root", F.coalesce("root", "class"))
    groups = placed.groupBy("root").agg(F.min("first_id").alias("cluster_id"), F.sum("n").alias("cluster_size"), F.min(F.struct("first_id", "class")).getField("class").alias("head"))
    owned = stored(placed.join(groups, "root").select("class", "cluster_id", "cluster_size", F.coalesce("links", F.lit(0).cast("long")).alias("links"), (F.col("class") == F.col("head")).alias("leads"), "first_id"), "owned")
    out = all_rows.select("doc_id", "tag", "class").join(owned, "class")
    return out.withColumn("kept", F.col("leads") & (F.col("doc_id") == F.col("first_id"))).select("doc_id", "tag", "cluster_id", "cluster_size", "links", "kept")
