"""Hash trees and a vector commitment: the coarse verification the check codes are compared with."""

from __future__ import annotations

import hashlib
import secrets
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tierbit.sources.storage import stored


def levels_of(n: int) -> int:
    return max(0, (n - 1).bit_length())


def build(digests: DataFrame, n: int, step: int = 10) -> DataFrame:
    """(level, idx, hash) from (pos, digest) with positions 0..n-1; a last node without a sibling goes up unchanged.

    A pass gathers 2 ** step nodes to a row and makes ``step`` levels above them there; what it
    makes is written, so passes don't repeat each other's work.
    """
    level = digests.select(F.col("pos").alias("idx"), F.col("digest").alias("hash"))
    out, done = [level.select(F.lit(0).alias("level"), "idx", "hash")], 0
    while done < levels_of(n):
        k = min(step, levels_of(n) - done)
        rows = level.groupBy(F.shiftright("idx", k).alias("g")).agg(F.array_sort(F.collect_list(F.struct("idx", "hash"))).alias("x")).select("g", F.transform("x", lambda x: x["hash"]).alias("a0"))
        for i in range(k):
            rows = rows.withColumn(f"a{i + 1}", F.expr(f"transform(sequence(0, (size(a{i}) - 1) div 2), j -> if(2 * j + 1 < size(a{i}), sha2(unhex(concat(a{i}[cast(2 * j as int)], a{i}[cast(2 * j + 1 as int)])), 256), a{i}[cast(2 * j as int)]))"))
        rows = stored(rows.drop("a0"), "hash-tree")
        for i in range(1, k + 1):
            nodes = rows.select(F.shiftleft("g", k - i).alias("first"), F.posexplode(f"a{i}").alias("i", "hash"))
            out.append(nodes.select(F.lit(done + i).alias("level"), (F.col("first") + F.col("i")).alias("idx"), "hash"))
        level, done = rows.select(F.col("g").alias("idx"), F.element_at(f"a{k}", 1).alias("hash")), done + k
    return reduce(DataFrame.unionByName, out)


def proof(tree: DataFrame, i: int, n: int) -> list[tuple[int, str]]:
    """Siblings from leaf i up: (1 if the sibling is on the right, hash). Reads one node of each level."""
    wanted = [(level, (i >> level) ^ 1) for level in range(levels_of(n))]
    cond = " OR ".join(f"(level = {level} AND idx = {idx})" for level, idx in wanted) or "false"
    got = {(r["level"], r["idx"]): r["hash"] for r in tree.where(cond).collect()}
    return [(1 if idx & 1 else 0, got[level, idx]) for level, idx in wanted if (level, idx) in got]


def check(leaf: str, path: list[tuple[int, str]], root: str) -> bool:
    h = leaf
    for right, sibling in path:
        a, b = (h, sibling) if right else (sibling, h)
        h = hashlib.sha256(bytes.fromhex(a + b)).hexdigest()
    return h == root


def proof_bytes(n: int) -> int:
    return 32 * levels_of(n)


class VectorCommitment:
    """A polynomial through the vector's values, committed by its value at a secret point.

    A teaching form with a designated verifier (who holds the secret), over a prime field:
    an opening is one field element whatever the vector's length. For small vectors on the
    driver; not for production use.
    """

    P = 2**127 - 1

    def __init__(self, values: list[int], secret: int | None = None):
        self.values, self.secret = [v % self.P for v in values], secret or secrets.randbelow(self.P - 1) + 1
        self.commitment = self._at(self.secret)

    def _at(self, x: int) -> int:
        n, total = len(self.values), 0
        for i, v in enumerate(self.values):
            num = den = 1
            for j in range(n):
                if j != i:
                    num, den = num * (x - j) % self.P, den * (i - j) % self.P
            total = (total + v * num * pow(den, -1, self.P)) % self.P
        return total

    def open(self, i: int) -> tuple[int, int]:
        """(value, witness): the witness is (f(s) - f(i)) / (s - i)."""
        v = self.values[i]
        return v, (self.commitment - v) * pow(self.secret - i, -1, self.P) % self.P

    @classmethod
    def verify(cls, commitment: int, secret: int, i: int, value: int, witness: int) -> bool:
        return (commitment - value) % cls.P == witness * (secret - i) % cls.P
