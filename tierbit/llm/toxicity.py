"""Toxicity by weak supervision.

Voters fire or don't on a text: lists of words and stems found in labelled rows (those most
over-represented in toxic ones, dealt over several lists), thresholds on how many listed words
occur, and patterns (shouting, exclamations, density). A generative label model over all
documents' vote patterns estimates how often each voter fires for either class by
expectation maximisation, with labelled rows held at their labels; voters that stay
correlated within a class are modelled jointly, so echoes don't count twice. A linear
classifier over hashed words and votes learns the model's posterior labels, and two
calibration parameters turn its margin into a probability.

The labelled sample is bounded (``per_class`` rows of either label); vote patterns count
all documents and are at most 2 ** voters. Texts are read whole. A null text is empty and
gets a score like any other; conflicting labels of one id count as toxic; of several texts
of one labelled id the greatest teaches; columns other than id and text, whatever their
names, are not read; with no labelled rows of both classes every score is 0. An empty table
gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tierbit.llm.common import lean

from tierbit.llm.neardup import _powers, mix

LISTS, BITS = 6, 16
_FOLD = bytes(c if 97 <= c <= 122 or c >= 128 else c + 32 if 65 <= c <= 90 else 32 for c in range(256))


PREFIXES = (4, 5, 6)


def words_of(text: str) -> tuple[np.ndarray, bytes, np.ndarray, np.ndarray]:
    """Hashes of the runs of letters: whole, then their first 4, 5 and 6 bytes (0 where shorter), one row each; with the folded bytes and where each run lies."""
    folded = text.lower().encode("utf-8", "replace").translate(_FOLD)
    raw = np.frombuffer(folded, np.uint8)
    if not len(raw):
        none = np.zeros(0, np.int64)
        return np.zeros((1 + len(PREFIXES), 0), np.uint64), folded, none, none
    up, down = _powers(len(raw) + 1)
    gaps = np.flatnonzero(raw == 32)
    starts, ends = np.concatenate([[0], gaps + 1]), np.concatenate([gaps, [len(raw)]])
    real = ends > starts
    starts, ends = starts[real], ends[real]
    sums = np.concatenate([[np.uint64(0)], np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], dtype=np.uint64)])
    rows = [mix((sums[ends] - sums[starts]) * down[starts])]
    for n in PREFIXES:
        cut = np.minimum(starts + n, len(raw))
        rows.append(np.where(ends - starts > n, mix((sums[cut] - sums[starts]) * down[starts] + np.uint64(n << 32)), np.uint64(0)))
    return np.stack(rows), folded, starts, ends


@dataclass
class Lexicon:
    """Listed words and stems by hash, ascending, and the list each belongs to."""

    hashes: np.ndarray
    owner: np.ndarray
    words: list[str] = field(default_factory=list)

    def sieve(self) -> np.ndarray:
        """Which top 20 bits a listed hash has."""
        if not hasattr(self, "_sieve"):
            self._sieve = np.zeros(1 << 20, bool)
            self._sieve[(self.hashes >> np.uint64(44)).astype(np.int64)] = True
        return self._sieve

    @property
    def voters(self) -> list[str]:
        return [f"list {i}" for i in range(LISTS)] + ["two", "three", "six", "dense", "shout", "exclaim"]

    def votes(self, text: str, hashes: np.ndarray | None = None) -> tuple[int, int]:
        """(votes as bits, listed words in the text)."""
        h = words_of(text)[0] if hashes is None else hashes
        bits = hits = 0
        n_words = h.shape[1]
        if n_words and len(self.hashes):
            maybe = self.sieve()[(h >> np.uint64(44)).astype(np.int64)]
            row, word = np.nonzero(maybe)
            at = np.minimum(np.searchsorted(self.hashes, h[row, word]), len(self.hashes) - 1)
            real = self.hashes[at] == h[row, word]
            hits = len(np.unique(word[real]))
            for i in np.unique(self.owner[at[real]]):
                bits |= 1 << int(i)
        raw = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
        shout = int(((raw >= 65) & (raw <= 90)).sum()) * 2 > max(1, len(raw))
        for i, on in enumerate((hits >= 2, hits >= 3, hits >= 6, hits * 100 >= max(1, n_words), shout, text.count("!") * 50 > max(1, n_words))):
            bits |= bool(on) << (LISTS + i)
        return bits, hits


def find_lexicon(rows: list[tuple[np.ndarray, int]], names: dict[int, bytes], most: int = 240, risk: float = 0.01) -> Lexicon:
    """Words and stems found in toxic rows far more often than chance allows.

    Chance is a binomial with 1.3 times the rows' toxic share (languages differ), bounded by
    its exponent, and shared over all words tried: ``risk`` is that of one false entry. A word
    that starts with a listed stem adds nothing and is left out.
    """
    sides = []
    for y in (1, 0):
        sets = [np.unique(h[h != 0]) for h, label in rows if label == y]
        words, n = np.unique(np.concatenate(sets), return_counts=True) if sets else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
        sides.append((dict(zip(words.tolist(), n.tolist())), len(sets)))
    (a, n_a), (b, n_b) = sides
    scored, p = [], min(0.9, 1.3 * n_a / max(1, n_a + n_b))
    bar = np.log(max(1, len(a)) / risk)
    for w, x in a.items():
        y = b.get(w, 0)
        share = x / (x + y)
        if share > p:
            excess = (x + y) * (share * np.log(share / p) + (1 - share) * np.log(max(1 - share, 1e-300) / (1 - p)))
            if excess >= bar:
                scored.append((-excess, len(names[w]), names[w], w))
    top, listed = [], set()
    for _, _, name, w in sorted(scored):
        if len(top) < most and not any(name[:n] in listed for n in range(1, len(name) + 1)):
            top.append(w)
            listed.add(name)
    owner = {w: i % LISTS for i, w in enumerate(top)}
    order = sorted(top)
    return Lexicon(np.array(order, np.uint64), np.array([owner[w] for w in order], np.int64), [names[w].decode("utf-8", "replace") for w in order])


class LabelModel:
    """Classes' firing rates over groups of voters; groups of more than one hold correlated voters."""

    def __init__(self, voters: int):
        self.groups: list[list[int]] = [[j] for j in range(voters)]
        self.prior, self.tables = 0.1, []

    def _codes(self, masks: np.ndarray) -> list[np.ndarray]:
        return [sum(((masks >> j) & 1) << i for i, j in enumerate(g)) for g in self.groups]

    def posterior(self, masks: np.ndarray) -> np.ndarray:
        z = np.full(len(masks), np.log(self.prior / (1 - self.prior)))
        for code, table in zip(self._codes(masks), self.tables):
            z += np.log(table[1, code] / table[0, code])
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))

    def _maximise(self, masks, n, q) -> None:
        self.prior = float(np.clip((n * q).sum() / n.sum(), 1e-4, 1 - 1e-4))
        self.tables = []
        for g, code in zip(self.groups, self._codes(masks)):
            t = np.stack([np.bincount(code, n * w, 1 << len(g)) for w in (1 - q, q)]) + 0.5
            self.tables.append(t / t.sum(axis=1, keepdims=True))

    def fit(self, masks: np.ndarray, n: np.ndarray, known: np.ndarray, labels: np.ndarray, passes: int = 30) -> LabelModel:
        """EM over pattern counts, with known rows' classes held; then once more with correlated voters joined."""
        anchor = 1.0
        for joined in (False, True):
            if joined:
                self.groups = self.correlated(masks, n, self.posterior(masks))
            self._maximise(known, np.full(len(known), anchor), labels.astype(float))
            for _ in range(passes):
                q = self.posterior(masks)
                self._maximise(np.concatenate([masks, known]), np.concatenate([n.astype(float), np.full(len(known), anchor)]), np.concatenate([q, labels]))
        return self

    def accuracies(self) -> list[tuple[list[int], np.ndarray]]:
        return list(zip(self.groups, self.tables))

    def correlated(self, masks, n, q, least: float = 0.2, most: int = 5) -> list[list[int]]:
        votes = np.stack([(masks >> g[0]) & 1 for g in self.groups], 1).astype(float)
        pairs = []
        for w in (n * q, n * (1 - q)):
            mean = (w[:, None] * votes).sum(0) / max(w.sum(), 1e-9)
            d = votes - mean
            cov = (w[:, None] * d).T @ d / max(w.sum(), 1e-9)
            sd = np.sqrt(np.maximum(np.diag(cov), 1e-9))
            pairs.append(np.abs(cov / sd[:, None] / sd[None, :]) * (sd[:, None] > 1e-4) * (sd[None, :] > 1e-4))
        strength = np.maximum(*pairs)
        group = {j: [j] for j in range(votes.shape[1])}
        for r, i, j in sorted(((strength[i, j], i, j) for i in range(votes.shape[1]) for j in range(i)), reverse=True):
            if r >= least and group[i] is not group[j] and len(group[i]) + len(group[j]) <= most:
                joint = group[i] + group[j]
                for m in joint:
                    group[m] = joint
        return [list(g) for g in {id(g): sorted(g) for g in group.values()}.values()]


@dataclass
class Scorer:
    lexicon: Lexicon
    weights: np.ndarray
    a: float = 1.0
    b: float = 0.0

    def features(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        h = words_of(text)[0]
        bits, hits = self.lexicon.votes(text, h)
        at, n = np.unique((h[h != 0] >> np.uint64(64 - BITS)).astype(np.int64), return_counts=True)
        x = np.log1p(n)
        x = x / max(1e-9, float(np.sqrt(x @ x)))
        k = len(self.lexicon.voters)
        on = [i for i in range(k) if bits >> i & 1]
        return np.concatenate([at, (1 << BITS) + np.array(on, np.int64), [(1 << BITS) + k, (1 << BITS) + k + 1]]).astype(np.int64), np.concatenate([x, np.ones(len(on)), [min(hits, 20) / 5, 1.0]])

    def margin(self, text: str) -> float:
        at, x = self.features(text)
        return float(x @ self.weights[at])

    def score(self, text: str | None) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.a * self.margin(text or "") + self.b, -40, 40))))


def train_linear(rows: list[tuple[np.ndarray, np.ndarray, float]], size: int, passes: int = 6, rate: float = 0.3, l2: float = 1e-5, seed: int = 3) -> np.ndarray:
    """Logistic regression on soft labels with steps per coordinate."""
    w, g2, rng = np.zeros(size), np.full(size, 1e-2), np.random.default_rng(seed)
    for _ in range(passes):
        for i in rng.permutation(len(rows)):
            at, x, y = rows[i]
            g = (1 / (1 + np.exp(-np.clip(x @ w[at], -40, 40))) - y) * x + l2 * w[at]
            g2[at] += g * g
            w[at] -= rate * g / np.sqrt(g2[at])
    return w


def calibrate(margins: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and offset with the least log loss, by Newton steps."""
    ab = np.array([1.0, 0.0])
    x = np.stack([margins, np.ones(len(margins))], 1)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ ab, -40, 40)))
        h = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
        ab = ab - np.clip(np.linalg.solve(h, x.T @ (p - y) + 1e-3 * (ab - [1, 0])), -2, 2)
    return float(ab[0]), float(ab[1])


def fit(docs: DataFrame, labels: DataFrame, learnable: Column, per_class: int = 2500, key: str = "doc_id", text: str = "text", label: str = "toxic") -> Scorer | None:
    """Learn from labelled rows whose id satisfies ``learnable`` (a condition on doc_id)."""
    ids = labels.select(F.col(key).alias("doc_id"), F.col(label).alias("y")).where(F.col("doc_id").isNotNull() & F.col("y").isNotNull()).where(learnable).groupBy("doc_id").agg(F.max("y").alias("y"))
    counts = {r["y"]: r["count"] for r in ids.groupBy("y").count().collect()}
    if not counts.get(1) or not counts.get(0):
        return None
    chance = F.pmod(F.xxhash64(F.lit(11), "doc_id"), F.lit(1 << 30)) / float(1 << 30)
    chosen = ids.where((F.col("y").isin(0, 1)) & (chance < F.when(F.col("y") == 1, 1.2 * per_class / counts[1]).otherwise(1.2 * per_class / counts[0]))).limit(4 * per_class)
    sample = docs.select(F.col(f"`{key}`").alias("doc_id"), F.col(f"`{text}`").alias("text")).join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.max("text").alias("text"), F.max("y").alias("y")).collect()
    sample = sorted(((r["doc_id"], r["text"] or "", int(r["y"])) for r in sample), key=lambda r: r[0])
    if len({r[2] for r in sample}) < 2:
        return None
    sample = list({t: (i, t, y) for i, t, y in reversed(sample)}.values())[::-1]  # copies teach nothing twice
    names, rows = {}, []
    for _, t, y in sample:
        h, folded, starts, ends = words_of(t)
        if y:
            for row, n in zip(h, (None, *PREFIXES)):
                names.update({w: folded[s : e if n is None else s + n] for w, s, e in zip(row.tolist(), starts.tolist(), ends.tolist()) if w})
        rows.append((h, y))
    lexicon = find_lexicon([r for i, r in enumerate(rows) if i % 4], names)
    masks = np.array([lexicon.votes(t, h)[0] for (_, t, _), (h, _) in zip(sample, rows)], np.int64)
    y = np.array([r[2] for r in sample])
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def patterns(batches):
        total: dict[int, int] = {}
        for b in batches:
            for t in b.column("text"):
                m = shared.value.votes(t.as_py() or "")[0]
                total[m] = total.get(m, 0) + 1
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int64()), pa.array(list(total.values()), pa.int64())], ["mask", "n"])

    seen = lean(docs).select(F.col(f"`{text}`").alias("text")).mapInArrow(patterns, "mask long, n long").groupBy("mask").agg(F.sum("n").alias("n")).collect()
    seen = sorted((r["mask"], r["n"]) for r in seen)
    model = LabelModel(len(lexicon.voters)).fit(np.array([m for m, _ in seen], np.int64), np.array([n for _, n in seen], np.int64), masks, y)
    soft = model.posterior(masks)
    scorer = Scorer(lexicon, np.zeros((1 << BITS) + len(lexicon.voters) + 2))
    made = [scorer.features(t) for _, t, _ in sample]
    scorer.weights = train_linear([(*m, float(s)) for i, (m, s) in enumerate(zip(made, soft)) if i % 4], len(scorer.weights))
    margins = np.array([x @ scorer.weights[at] for at, x in made])
    held = np.arange(len(sample)) % 4 == 0
    if len(set(y[held])) < 2:
        held[:] = True
    scorer.a, scorer.b = calibrate(margins[held], y[held])
    # the sample holds both labels evenly: give it back their own shares
    share = counts[1] / (counts[0] + counts[1])
    seen_share = float(np.clip(y[held].mean(), 1e-3, 1 - 1e-3))
    scorer.b += float(np.log(share / (1 - share)) - np.log(seen_share / (1 - seen_share)))
    return scorer


def score(docs: DataFrame, scorer: Scorer | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and score of every row."""
    rows = docs.select(F.col(f"`{key}`").alias("doc_id"), F.col(f"`{text}`").alias("text"))
    if scorer is None:
        return rows.select("doc_id", F.lit(0.0).alias("score"))
    shared = docs.sparkSession.sparkContext.broadcast(scorer)

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([shared.value.score(t.as_py()) for t in b.column("text")], pa.float64())], ["doc_id", "score"])

    from pyspark.sql import types as T

    return lean(rows).mapInArrow(run, T.StructType([rows.schema["doc_id"], T.StructField("score", T.DoubleType())]))
