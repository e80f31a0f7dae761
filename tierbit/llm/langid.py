"""Language identification by sparse multinomial logistic regression.

Features are TF-IDF weights of hashed character n-grams (1 to 3 letters, lower case, runs
of anything but letters as one space), scaled to length one. Document frequencies count
every learnable text. Weights are learned by follow-the-regularised-leader with elastic
net on ``per_class`` distinct texts of each language at most (the documented bound of the
training sample; copies neither count nor thin it), three quarters of them; the last quarter sets the temperature that
calibrates the probabilities.

A null text or one without a letter is ``und`` with score 0, and so is every text if
nothing can be learned (no labelled rows). Texts are scored whole, very long ones in
chunks. Rows with a null or repeated id are scored like any others; an empty table gives
no rows.
"""

from __future__ import annotations

import sys
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tierbit.llm.common import lean, stored, without

BITS, ORDERS, CHUNK = 15, 3, 1 << 20
_TABLE: list[np.ndarray] = []


def _letters() -> np.ndarray:
    """Code point to lower-case letter, or a space."""
    if not _TABLE:
        table = np.full(sys.maxunicode + 1, 32, np.uint32)
        for c in range(sys.maxunicode + 1):
            if chr(c).isalpha():
                low = chr(c).lower()
                table[c] = ord(low) if len(low) == 1 else c
        _TABLE.append(table)
    return _TABLE[0]


def grams(text: str) -> np.ndarray:
    """Counts of hashed n-grams over the whole text."""
    counts = np.zeros(1 << BITS, np.float32)
    for at in range(0, len(text), CHUNK):
        codes = _letters()[np.frombuffer(text[max(0, at - ORDERS + 1) : at + CHUNK].encode("utf-32-le", "replace"), np.uint32)]
        space = codes == 32
        codes = np.concatenate([[32], codes[~(space & np.roll(space, 1))] if len(codes) > 1 else codes, [32]]).astype(np.uint32)
        h = np.zeros(len(codes), np.uint32)
        for n in range(ORDERS):
            h = h[: len(codes) - n] * np.uint32(0x01000193) + codes[n:] + np.uint32(n + 1)
            counts += np.bincount((h * np.uint32(0x9E3779B1)) >> np.uint32(32 - BITS), minlength=1 << BITS)
    return counts


@dataclass
class Model:
    classes: list[str]
    idf: np.ndarray
    weights: np.ndarray
    bias: np.ndarray
    temperature: float = 1.0

    def features(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        counts = grams(text)
        at = np.flatnonzero(counts)
        x = (1 + np.log(counts[at])) * self.idf[at]
        return at, x / max(float(np.sqrt(x @ x)), 1e-12)

    def logits(self, at: np.ndarray, x: np.ndarray) -> np.ndarray:
        return x @ self.weights[at] + self.bias

    def predict(self, text: str | None) -> tuple[str, float]:
        if not self.classes or not text or not any(map(str.isalpha, text)):
            return "und", 0.0
        p = softmax(self.logits(*self.features(text)) / self.temperature)
        best = int(p.argmax())
        return self.classes[best], float(p[best])


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max())
    return e / e.sum()


def follow_the_leader(rows: list[tuple[np.ndarray, np.ndarray, int]], size: int, classes: int, passes: int = 4, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.5, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Weights and bias; each coordinate is solved from its gradient sums, most stay at zero."""
    z, n = np.zeros((size + 1, classes), np.float64), np.zeros((size + 1, classes), np.float64)

    def solved(z, n):
        return np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((beta + np.sqrt(n)) / alpha + l2))

    rng = np.random.default_rng(seed)
    for _ in range(passes):
        for i in rng.permutation(len(rows)):
            at, x, y = rows[i]
            at, x = np.append(at, size), np.append(x, 1.0)
            zi, ni = z[at], n[at]
            w = solved(zi, ni)
            p = softmax(x @ w)
            p[y] -= 1
            g = x[:, None] * p
            sigma = (np.sqrt(ni + g * g) - np.sqrt(ni)) / alpha
            z[at], n[at] = zi + g - sigma * w, ni + g * g
    w = solved(z, n)
    return w[:-1], w[-1]


def calibrate(logits: np.ndarray, y: np.ndarray) -> float:
    """The temperature with the least log loss, by golden section over its logarithm."""

    def loss(t: float) -> float:
        z = logits / np.exp(t)
        z = z - z.max(axis=1, keepdims=True)
        return float((np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(y)), y]).mean())

    low, high, ratio = -3.0, 2.0, (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = high - ratio * (high - low), low + ratio * (high - low)
        low, high = (low, b) if loss(a) < loss(b) else (a, high)
    return float(np.exp((low + high) / 2))


def fit(docs: DataFrame, learnable: Column, per_class: int = 400, text: str = "text", lang: str = "lang") -> Model:
    """Learn from rows where ``learnable`` holds and the language isn't null."""
    rows = docs.where(learnable & F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(lang).alias("lang"), F.col(text).alias("text"))
    distinct = stored(rows.select("lang", F.xxhash64(F.lit(3), "text").alias("tag")).distinct(), "language-texts")
    counts = {r[0]: r[1] for r in distinct.groupBy("lang").count().collect()}
    classes = sorted(counts)
    if not classes:
        return Model([], np.zeros(0), np.zeros((0, 0)), np.zeros(0))

    def frequencies(batches):
        total = np.zeros(1 << BITS, np.int64)
        for b in batches:
            for t in b.column("text"):
                total += grams(t.as_py()) > 0
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], ["gram", "n"])

    df = np.zeros(1 << BITS)
    for g, n in lean(rows.select("text")).mapInArrow(frequencies, "gram int, n long").groupBy("gram").agg(F.sum("n")).collect():
        df[g] = n
    idf = (np.log((1 + rows.count()) / (1 + df)) + 1).astype(np.float32)
    share = F.create_map(*[F.lit(x) for c in classes for x in (c, min(1.0, 1.3 * per_class / counts[c]))])
    chance = (F.pmod(F.xxhash64(F.lit(3), "text"), F.lit(1 << 30)) / float(1 << 30)) <= share[F.col("lang")]
    sample = rows.where(chance).dropDuplicates(["lang", "text"]).limit(per_class * len(classes) * 2).collect()
    held = {c: [] for c in classes}
    for r in sorted(sample, key=lambda r: r["text"]):
        if len(held[r["lang"]]) < per_class:
            held[r["lang"]].append(r["text"])
    model = Model(classes, idf, np.zeros((1 << BITS, len(classes))), np.zeros(len(classes)))
    made = [(*model.features(t), classes.index(c), i) for c in classes for i, t in enumerate(held[c])]
    fitted = [m[:3] for m in made if m[3] % 4] or [m[:3] for m in made]
    model.weights, model.bias = follow_the_leader(fitted, 1 << BITS, len(classes))
    model.weights = model.weights.astype(np.float32)
    rest = [m for m in made if m[3] % 4 == 0]
    model.temperature = calibrate(np.array([model.logits(m[0], m[1]) for m in rest]), np.array([m[2] for m in rest]))
    return model


def identify(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """The rows of ``docs`` with lang_pred and score (columns of those names are replaced)."""
    docs = without(docs, "lang_pred", "score")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = docs.columns
    wrapped = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), F.col(f"`{text}`").alias("text"))

    def score(batches):
        own = shared.value
        for b in batches:
            got = [own.predict(t.as_py()) for t in b.column("text")]
            yield pa.RecordBatch.from_arrays([b.column("row"), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], ["row", "lang_pred", "score"])

    from pyspark.sql import types as T

    schema = T.StructType([wrapped.schema["row"], T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return lean(wrapped).mapInArrow(score, schema).select("row.*", "lang_pred", "score")
