"""Mixing sources to target weights by iterative proportional fitting.

Documents fall into cells (source, language, topic) with a mass of tokens. Raking scales
the cells in turn to the target share of each source, language and topic until all three
hold; a cell's factor is its raked share over its own. Each document is then sampled by
the calibrated probability factor x c, where c is such that the expected tokens are
``budget`` times the table's. With ``repeats`` a probability above 1 gives whole copies
and a chance of one more, and expected shares meet the targets exactly; without, it is cut
at 1 and c is solved again for the rest, so a scarce cell may fall short.

Default targets flatten the present shares (share ** power, rescaled). Chance comes from
an MD5 of seed and id, so a retried task samples the same rows, and rows that repeat an id
share its fate. Only cell totals reach the driver, and only up to ``max_cells``; beyond,
the same raking and the same c come from joins and sums of the cell table (results agree to
rounding). Nulls in a grouping column are the group ``<null>``; a null text has one token;
texts are read whole; input columns named like the result's (``topic``, ``tokens``,
``factor``, ``prob``, ``copies``) are not read, and ``carry`` returns them inside ``row``; an
empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tierbit.llm.common import stored

DIMS = ["source", "lang", "topic"]


@dataclass
class Mix:
    powers: dict[str, float] = field(default_factory=lambda: {"source": 0.6, "lang": 0.8, "topic": 0.9})
    targets: dict[str, dict[str, float]] = field(default_factory=dict)
    rounds: int = 30
    budget: float = 0.7
    repeats: bool = False
    seed: int = 7
    max_cells: int = 200_000


def topic_of(text: Column) -> Column:
    """A coarse topic by form; any column of one's own may stand in for it."""
    return F.when(F.contains(text, F.lit("License")), "legal").when(F.contains(text, F.lit(" = ")), "code").when(F.contains(text, F.lit(" | ")), "table").when(F.char_length(text) >= 4000, "long").otherwise("prose")


def tokens_of(text: Column) -> Column:
    """Tokens as four characters each, and one for the end."""
    return (F.floor(F.char_length(text) / 4) + 1).cast("long")


def celled(docs: DataFrame, key: str = "doc_id", text: str = "text", topic: Column | None = None, carry: bool = False) -> DataFrame:
    row = [F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")] if carry else []
    t = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    named = lambda c: F.coalesce(F.col(f"`{c}`").cast("string"), F.lit("<null>")).alias(c)
    return docs.select(F.col(f"`{key}`").alias("doc_id"), named("source"), named("lang"), (topic_of(t) if topic is None else F.coalesce(topic, F.lit("<null>"))).alias("topic"), tokens_of(t).alias("tokens"), *row)


def _targets(cells: list[tuple], mix: Mix) -> list[dict[str, float]]:
    out = []
    for i, dim in enumerate(DIMS):
        mass: dict[str, float] = {}
        for c in cells:
            mass[c[i]] = mass.get(c[i], 0.0) + c[3]
        goal = {k: v for k, v in mix.targets[dim].items() if k in mass} if dim in mix.targets else {k: (m / sum(mass.values())) ** mix.powers.get(dim, 1.0) for k, m in mass.items()}
        total = sum(goal.values())
        out.append({k: goal.get(k, 0.0) / total for k in mass})
    return out


def rake(cells: list[tuple], mix: Mix) -> list[float]:
    """Raked share of each cell (source, lang, topic, tokens)."""
    goals, whole = _targets(cells, mix), sum(c[3] for c in cells)
    w = [c[3] / whole for c in cells]
    for _ in range(mix.rounds):
        for i in range(len(DIMS)):
            have: dict[str, float] = {}
            for c, x in zip(cells, w):
                have[c[i]] = have.get(c[i], 0.0) + x
            w = [x * goals[i][c[i]] / have[c[i]] if have[c[i]] else 0.0 for c, x in zip(cells, w)]
    return w


def _rake_frames(cells: DataFrame, mix: Mix) -> DataFrame:
    """The same raking with joins and sums, for cell tables too large for the driver."""
    whole = cells.agg(F.sum("tokens")).first()[0]
    w = cells.withColumn("w", F.col("tokens") / float(whole))
    goals = {}
    for dim in DIMS:
        own = w.groupBy(dim).agg(F.sum("w").alias("share"))
        if dim in mix.targets:
            given = cells.sparkSession.createDataFrame(list(mix.targets[dim].items()), f"{dim} string, goal double")
            own = own.join(given, dim, "left").select(dim, F.coalesce("goal", F.lit(0.0)).alias("goal"))
        else:
            own = own.select(dim, F.pow("share", F.lit(mix.powers.get(dim, 1.0))).alias("goal"))
        total = own.agg(F.sum("goal")).first()[0]
        goals[dim] = stored(own.withColumn("goal", F.col("goal") / total), "goal")
    for n in range(mix.rounds):
        for dim in DIMS:
            have = w.groupBy(dim).agg(F.sum("w").alias("have"))
            w = w.join(have, dim).join(goals[dim], dim).withColumn("w", F.when(F.col("have") > 0, F.col("w") * F.col("goal") / F.col("have")).otherwise(0.0)).drop("have", "goal")
        w = stored(w, "raked") if n % 2 else w
    return w.withColumn("factor", F.col("w") * whole / F.col("tokens"))


def calibrate(tokens: list[float], factors: list[float], mix: Mix) -> float:
    """c with expected tokens = budget x all tokens."""
    goal = mix.budget * sum(tokens)
    if mix.repeats:
        return goal / max(1e-300, sum(t * f for t, f in zip(tokens, factors)))
    c, low, high = 0.0, 0.0, 1.0
    expect = lambda c: sum(t * min(1.0, c * f) for t, f in zip(tokens, factors))
    while expect(high) < goal * (1 - 1e-12) and high < 2.0**60:
        high *= 2
    for _ in range(200):
        c = (low + high) / 2
        low, high = (c, high) if expect(c) < goal else (low, c)
    return c


def _calibrate_frames(cells: DataFrame, mix: Mix) -> float:
    """The same c over a table of cells: it rises as cells reach probability 1, until no other does."""
    total, mass = cells.agg(F.sum("tokens"), F.sum(F.col("tokens") * F.col("factor"))).first()
    goal = mix.budget * total
    c = goal / max(1e-300, mass)
    while not mix.repeats:
        cut = F.col("factor") * c >= 1
        whole, rest = cells.agg(F.coalesce(F.sum(F.when(cut, F.col("tokens"))), F.lit(0)), F.coalesce(F.sum(F.when(~cut, F.col("tokens") * F.col("factor"))), F.lit(0.0))).first()
        higher = (goal - whole) / rest if rest > 0 else c
        if higher <= c * (1 + 1e-14):
            break
        c = higher
    return c


def chance(seed: int, key: str = "doc_id") -> Column:
    """Uniform in [0, 1) from the MD5 of seed and id."""
    digest = F.md5(F.concat_ws(":", F.lit(seed), F.coalesce(F.col(key).cast("string"), F.lit("null"))).cast("binary"))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / float(1 << 32)


def mixed(docs: DataFrame, mix: Mix | None = None, key: str = "doc_id", text: str = "text", topic: Column | None = None, carry: bool = False) -> DataFrame:
    """doc_id, source, lang, topic, tokens, factor, prob, copies for every row; copies 0 drops it. ``carry`` adds the row."""
    mix, spark = mix or Mix(), docs.sparkSession
    rows = celled(docs, key, text, topic, carry)
    cells = stored(celled(docs, key, text, topic).groupBy(*DIMS).agg(F.sum("tokens").alias("tokens")), "cells")
    n = cells.count()
    if not n:
        return rows.select("*", *[F.lit(0.0).alias(c) for c in ("factor", "prob")], F.lit(0).cast("long").alias("copies"))
    if n <= mix.max_cells:
        held = sorted(tuple(r) for r in cells.select(*DIMS, "tokens").collect())
        whole = sum(c[3] for c in held)
        factors = [w * whole / c[3] for w, c in zip(rake(held, mix), held)]
        c = calibrate([x[3] for x in held], factors, mix)
        columns = [pa.array([x[i] for x in held], pa.string()) for i in range(len(DIMS))]
        priced = spark.createDataFrame(pa.table([*columns, pa.array(factors, pa.float64())], [*DIMS, "factor"]))  # rows would start Python workers of another kind
    else:
        priced = stored(_rake_frames(cells, mix), "factors")
        c = _calibrate_frames(priced, mix)
        priced = priced.select(*DIMS, "factor")
    p = F.col("factor") * c
    out = rows.join(F.broadcast(priced) if n <= 10_000 else priced, DIMS).withColumn("prob", p if mix.repeats else F.least(p, F.lit(1.0)))
    draw = F.floor("prob") + F.when(chance(mix.seed) < F.col("prob") - F.floor("prob"), 1).otherwise(0)
    return out.select("doc_id", *DIMS, "tokens", "factor", "prob", draw.cast("long").alias("copies"), *(["row"] if carry else []))
