"""Result verification by shortened digests: width choice, comparison, verdict, re-check, faults."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tierbit.functions.crc import WIDTHS, code_columns
from tierbit.operators import merkle
from tierbit.sources.ledger import digest, with_digest, with_rank

BLOCK = 1 << 16


def alpha(n: int, k: int) -> float:
    """Chance that a false row matches none of n codes."""
    return 1 - n / 2.0**k


def log_beta(n: int, k: int) -> float:
    """Logarithm of the chance that n codes are distinct: the sum of all n - 1 terms, by blocks, whatever n is."""
    if n > 2**k:
        return -math.inf
    return math.fsum(np.log1p(-np.arange(at, min(at + BLOCK, n)) / 2.0**k).sum() for at in range(1, n, BLOCK))


def choose_k(n: int, least_alpha: float, least_beta: float) -> int | None:
    """The smallest width that satisfies both thresholds; None: send whole digests."""
    for k in WIDTHS:
        if n / 2.0**k < 1 - least_alpha and log_beta(n, k) > math.log(least_beta):
            return k
    return None


@dataclass(frozen=True)
class Vo:
    """Codes (code_hi, code_lo) or whole digests (code_hex), with what the user needs to check them."""

    codes: DataFrame
    k: int | None
    n_h: int
    r: int
    expires: float = math.inf


def with_codes(df: DataFrame, k: int | None, r: int) -> DataFrame:
    """``df`` with the code of its ``digest`` column."""
    if k is None:
        return df.withColumn("code_hi", F.lit(0).cast("long")).withColumn("code_lo", F.lit(0).cast("long")).withColumn("code_hex", F.col("digest"))
    hi, lo = code_columns(F.col("digest"), k, r)
    return df.withColumn("code_hi", hi).withColumn("code_lo", lo).withColumn("code_hex", F.lit(""))


CODE = ["code_hi", "code_lo", "code_hex"]


def make_vo(chain: DataFrame, r: int, least_alpha: float = 1 - 1e-5, least_beta: float = 0.99, k: int | None = None, expires: float = math.inf) -> Vo:
    """The chain's answer: digests of the matching records, shortened. Only their number reaches the driver."""
    n = chain.count()
    k = k or choose_k(n, least_alpha, least_beta)
    return Vo(with_codes(chain, k, r).select(*CODE), k, n, r, expires)


def compare(vo: Vo, rows: DataFrame, cols: list[str]) -> DataFrame:
    """Full outer join of codes and the provider's rows as multisets: (pos, code, state) with state accepted, unexpected or missing."""
    tie = W.partitionBy(*CODE).orderBy(F.lit(1))
    own = with_codes(rows.withColumn("digest", digest(cols)), vo.k, vo.r).select("pos", *CODE).withColumn("tie", F.row_number().over(W.partitionBy(*CODE).orderBy("pos")))
    sent = vo.codes.withColumn("tie", F.row_number().over(tie)).withColumn("sent", F.lit(True))
    both = own.withColumn("given", F.lit(True)).join(sent, [*CODE, "tie"], "full")
    return both.select("pos", *CODE, F.when(F.col("given") & F.col("sent"), "accepted").when(F.col("given"), "unexpected").otherwise("missing").alias("state"))


def verdict(compared: DataFrame, gamma: float) -> DataFrame:
    """One row: n_r, n_h, n_acc, unexpected, missing and the behaviour: ok, B1, B2, B1+B2 or B3 (reject all)."""
    n = compared.agg(F.count_if(F.col("state") == "accepted").alias("n_acc"), F.count_if(F.col("state") == "unexpected").alias("unexpected"), F.count_if(F.col("state") == "missing").alias("missing"))
    n = n.withColumn("n_r", F.col("n_acc") + F.col("unexpected")).withColumn("n_h", F.col("n_acc") + F.col("missing"))
    low = F.when(F.col("n_r") == 0, F.col("n_h") > 0).otherwise(F.col("n_acc") < F.lit(gamma) * F.col("n_r"))
    kind = F.when(low, "B3").when((F.col("unexpected") > 0) & (F.col("missing") > 0), "B1+B2").when(F.col("unexpected") > 0, "B1").when(F.col("missing") > 0, "B2").otherwise("ok")
    return n.select("n_r", "n_h", "n_acc", "unexpected", "missing", kind.alias("behaviour"))


def leftover(compared: DataFrame, vo: Vo) -> Vo:
    """The codes no row matched, for a later answer under the same polynomial."""
    rest = compared.where("state = 'missing'").select(*CODE)
    return Vo(rest, vo.k, rest.count(), vo.r, vo.expires)


def recheck(rest: Vo, rows: DataFrame, cols: list[str], now: float) -> DataFrame:
    """Compare a new answer with the codes left over; no chain request. Refused once r has expired."""
    if now > rest.expires:
        raise ValueError("r has expired: ask the chain again with a new one")
    return compare(rest, rows, cols)


def inject(rows: DataFrame, mode: str, percent: int, col: str, seed: int = 0) -> DataFrame:
    """Rows as a faulty provider sends them: B1 adds altered rows, B2 hides some, B3 alters all. Chosen by pos."""
    pick = F.pmod(F.col("pos") * 7919 + seed, F.lit(100)) < percent
    fake = lambda df: df.withColumn(col, F.col(col) + 1)
    if mode == "B1":
        return rows.unionByName(fake(rows.where(pick)))
    if mode == "B2":
        return rows.where(~pick)
    if mode == "B3":
        return fake(rows)
    return rows


def agree(results: DataFrame) -> DataFrame:
    """(replica, pos) of all replicas: the answer hash most of them give, with their number."""
    votes = results.groupBy("replica").agg(F.count("*").alias("n"), F.sum(F.xxhash64("pos").cast("decimal(38,0)")).alias("mark"))
    return votes.groupBy("n", "mark").agg(F.count("*").alias("votes"), F.min("replica").alias("replica")).orderBy(F.desc("votes"), "replica").limit(1).select("replica", "n", "votes")


def coarse_root(rows: DataFrame, cols: list[str]) -> str | None:
    """The root of a hash tree over an answer in order of position; none for an empty one."""
    ordered = with_rank(with_digest(rows, cols).select("pos", "digest"), ["pos"], "at")
    n = ordered.count()
    if not n:
        return None
    tree = merkle.build(ordered.select(F.col("at").alias("pos"), "digest"), n)
    return tree.where(F.col("level") == merkle.levels_of(n)).first()["hash"]


def coarse(chain_rows: DataFrame, given: DataFrame, cols: list[str]) -> int:
    """Records accepted by comparing roots alone: all that were given, or none."""
    return given.count() if coarse_root(chain_rows, cols) == coarse_root(given, cols) else 0


def vo_bytes(n: int, k: int | None) -> int:
    return n * (256 if k is None else k) // 8


def saving(k: int) -> float:
    return 1 - k / 256


def fetch_hidden(rows: DataFrame, percent: int, seed: int = 0) -> DataFrame:
    """The rows that ``inject`` in mode B2 hides: what a second provider may send."""
    return rows.where(F.pmod(F.col("pos") * 7919 + seed, F.lit(100)) < percent)
