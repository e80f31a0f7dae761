"""Personal data by candidate gradient boosting, in DataFrame expressions only.

Generators with high recall propose spans of four kinds. Those of the base patterns that
pass their checks (address parts, Luhn sum, number of digits) are taken as they are. Wider
forms (local phone numbers, cards with other separators, spelled-out addresses, long network
addresses) are proposed where they are clear of those. All proposals, base and wide, passed
or failed, teach boosted depth-two trees which formats and contexts go with data that pass
their kind's public check (``valid``); the trees see small integer features, never the
checks. Wide proposals are then scored, and those at or above their kind's threshold,
calibrated for precision on the other half of the documents, are added.

Training reads every document: its data are counts of distinct feature vectors, whose
number is bounded by the product of the features' ranges (below ``CELLS``), not by the
input. Positions are code points, found by running sums over the pieces between matches in
short chunks, and overlaps by halving, so work follows the number of matches also where one
text holds very many. A null text is empty; rows with null or repeated ids are scored like
any others; other columns, whatever their names, are not read; proposals with equal scores
share their fate; an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tierbit.llm.common import stored

KINDS = ["email", "ip", "card", "phone"]
#: The base patterns, in forms that need no second look at a run of characters.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9]){15,}+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Wider forms of each kind.
WIDER = {
    "email": r"[A-Za-z0-9._%+-]{1,64} ?[\[(]at[\])] ?[A-Za-z0-9-]{1,63}(?: ?(?:[\[(]dot[\])]|\.) ?[A-Za-z0-9-]{1,63}){1,8}",
    "ip": r"(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])",
    "card": r"(?<![0-9])(?:[0-9]{4}[./_]){3}[0-9]{4}(?![0-9])|(?<![0-9])3[47][0-9]{2}[ -]?[0-9]{6}[ -]?[0-9]{5}(?![0-9])",
    "phone": r"(?<![0-9+(])(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9])",
}
GATES = {
    "email": lambda t: F.contains(t, F.lit("@")),
    "ip": lambda t: F.contains(t, F.lit(".")) & t.rlike("[0-9]"),
    "card": lambda t: t.rlike("[0-9]"),
    "phone": lambda t: F.contains(t, F.lit("+")),
    "wide email": lambda t: F.contains(t, F.lit("at)")) | F.contains(t, F.lit("at]")),
    "wide ip": lambda t: F.contains(t, F.lit(":")),
    "wide card": lambda t: t.rlike("[0-9]{4}"),
    "wide phone": lambda t: t.rlike("[0-9]{4}"),
}
SPAN = "array<struct<kind:int,s:int,e:int,hit:string,before:string,after:string,wide:int>>"
FEATURES = {"kind": 4, "wide": 2, "size": 6, "digits": 6, "marks": 5, "groups": 5, "before": 4, "after": 4, "cue": 5}
CELLS = 2 * 3 * math.prod(FEATURES.values())


CHUNK = 256


def _parts(values: str) -> Column:
    """Running sums of an array of integers within chunks: an array that grows by one costs its length each time, so none grows long."""
    return F.expr(
        f"transform(sequence(0, greatest(0, cast(ceil(size({values}) / {CHUNK}) as int) - 1)), c -> aggregate(slice({values}, c * {CHUNK} + 1, {CHUNK}),"
        " named_struct('at', 0, 'out', cast(array() as array<int>)), (a, x) -> named_struct('at', a.at + x, 'out', concat(a.out, array(a.at + x)))))"
    )


def _whole(parts: str) -> Column:
    """Running sums of the whole array, from those of its chunks."""
    before = f"aggregate({parts}, named_struct('at', 0, 'out', cast(array() as array<int>)), (a, p) -> named_struct('at', a.at + p.at, 'out', concat(a.out, array(a.at))), a -> a.out)"
    return F.expr(f"flatten(zip_with({parts}, {before}, (p, at) -> transform(p.out, x -> x + at)))")


def _matches(name: str, kind: int, wide: int) -> Column:
    """Spans of one pattern from its columns: hits, gaps, ends."""
    h, g, e = (f"{c}_{name}" for c in "hge")
    return F.expr(f"transform({h}, (h, i) -> named_struct('kind', {kind}, 's', {e}[i] - char_length(h), 'e', {e}[i], 'hit', h, 'before', right({g}[i], 24), 'after', left({g}[i + 1], 8), 'wide', {wide}))")


def _meets(kind: int) -> str:
    """Whether span w overlaps a valid base span of one kind, which ascend and don't overlap: by halving."""
    halve = "if(a.low >= a.high, a, if(s_{k}[(a.low + a.high) div 2] < w.e, named_struct('low', cast((a.low + a.high) div 2 as int) + 1, 'high', a.high), named_struct('low', a.low, 'high', cast((a.low + a.high) div 2 as int))))"
    return ("aggregate(sequence(0, cast(ceil(log2(size(s_{k}) + 1)) as int)), named_struct('low', 0, 'high', size(s_{k})), (a, _) -> " + halve + ", a -> if(a.low > 0, e_{k}[a.low - 1] > w.s, false))").replace("{k}", str(kind))


def _digits(hit: Column) -> Column:
    return F.regexp_replace(hit, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the check sum of card numbers."""
    n = F.char_length(digits)
    value = F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(F.reverse(digits), i, F.lit(1)).cast("int") * (2 - i % 2))
    return F.aggregate(value, F.lit(0), lambda t, v: t + F.when(v > 9, v - 9).otherwise(v)) % 10 == 0


def valid(span: Column) -> Column:
    """The public check of a span's kind: the base checks, and for wider forms those of numbering plans, address blocks and top-level names."""
    hit, digits = span["hit"], _digits(span["hit"])
    n = F.char_length(digits)
    part = lambda p: F.regexp_replace(p, "^0+(?=.)", "")
    address = F.forall(F.split(hit, r"\."), lambda p: F.when(F.char_length(part(p)) <= 3, part(p).cast("int") <= 255).otherwise(False))
    base = F.when(span["kind"] == 0, F.lit(True)).when(span["kind"] == 1, address).when(span["kind"] == 2, F.when(n.between(16, 19), luhn(digits)).otherwise(False)).otherwise(n.between(8, 15))
    wide = F.when(span["kind"] == 0, hit.rlike("[A-Za-z]{2,24}$")).when(span["kind"] == 1, hit.rlike("^(?:[23][0-9A-Fa-f]{3}|[Ff][CcDd][0-9A-Fa-f]{2}|[Ff][Ee]80):")).when(span["kind"] == 2, luhn(digits)).otherwise(digits.rlike("^[2-9][0-9]{2}[2-9][0-9]{6}$"))
    return F.when(span["wide"] == 1, wide).otherwise(base)


def proposals(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, fold, base (all base matches) and wide (proposals clear of valid base spans), each with ``ok``."""
    t = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    df = docs.select(F.col(f"`{key}`").alias("doc_id"), t.alias("text"))
    plain = {**{k: p for k, p in BASE.items()}, **{f"wide {k}": p for k, p in WIDER.items()}}
    names = {n: n.replace(" ", "_") for n in plain}
    none = F.array().cast("array<string>")
    df = df.select("*", *[F.when(GATES[n](F.col("text")), F.regexp_extract_all("text", F.lit(p), F.lit(0))).otherwise(none).alias(f"h_{names[n]}") for n, p in plain.items()])
    df = df.select("doc_id", "text", *[f"h_{n}" for n in names.values()], *[F.when(F.size(f"h_{names[n]}") > 0, F.split("text", p, -1)).otherwise(none).alias(f"g_{names[n]}") for n, p in plain.items()])
    df = df.select("*", *[F.expr(f"transform(h_{n}, (h, i) -> char_length(g_{n}[i]) + char_length(h))").alias(f"l_{n}") for n in names.values()])
    df = df.select("*", *[_parts(f"l_{n}").alias(f"p_{n}") for n in names.values()])
    df = df.select("*", *[F.when(F.size(f"h_{n}") > 0, _whole(f"p_{n}")).alias(f"e_{n}") for n in names.values()])
    checked = lambda spans: F.transform(spans, lambda x: x.withField("ok", valid(x)))
    out = df.select("doc_id", (F.xxhash64("text") % 2 == 0).alias("fold"), *[checked(_matches(k, i, 0)).alias(f"base_{i}") for i, k in enumerate(KINDS)], F.concat(*[_matches(f"wide_{k}", i, 1) for i, k in enumerate(KINDS)]).alias("wide"))
    edge = lambda i, c: F.transform(F.filter(f"base_{i}", lambda x: x["ok"]), lambda x: x[c])
    out = out.select("*", *[edge(i, c).alias(f"{c}_{i}") for i in range(len(KINDS)) for c in "se"])
    clear = F.expr(f"filter(wide, w -> not ({' or '.join(_meets(i) for i in range(len(KINDS)))}))")
    return out.select("doc_id", "fold", F.concat(*[f"base_{i}" for i in range(len(KINDS))]).alias("base"), checked(clear).alias("wide"))


def _bucket(value: Column, *edges: int) -> Column:
    out = F.lit(len(edges))
    for i in range(len(edges) - 1, -1, -1):
        out = F.when(value <= edges[i], i).otherwise(out)
    return out


def features(span: Column) -> dict[str, Column]:
    """Small integers within the ranges of FEATURES."""
    hit, before, after = span["hit"], span["before"], span["after"]
    n = F.char_length(_digits(hit))
    marks = F.char_length(F.regexp_replace(hit, "[A-Za-z0-9]", ""))
    edge = lambda c: F.when(c == "", 0).when(c.rlike(r"^\s$"), 1).when(c.rlike("^[A-Za-z0-9]$"), 2).otherwise(3)
    cue = F.lower(before)
    return {
        "kind": span["kind"],
        "wide": span["wide"],
        "size": _bucket(F.char_length(hit), 9, 12, 16, 20, 32),
        "digits": _bucket(n, 2, 7, 10, 15, 19),
        "marks": _bucket(marks, 0, 2, 4, 6),
        "groups": F.when(hit.rlike(r"[0-9]{3}[^0-9][0-9]{4}$"), 1).when(hit.rlike("[0-9]{4}[^0-9][0-9]{4}"), 2).when(hit.rlike("^[0-9]+$"), 3).when(hit.rlike("^[+(]"), 4).otherwise(0),
        "before": edge(F.right(before, F.lit(1))),
        "after": edge(F.left(after, F.lit(1))),
        "cue": F.when(cue.rlike("mail|contact|write"), 1).when(cue.rlike("phone|tel|call|fax|mobile"), 2).when(cue.rlike("card|visa|pay|account"), 3).when(cue.rlike("ip|host|server|addr"), 4).otherwise(0),
    }


class Trees:
    """Boosted depth-two trees over cells of (features, positives, negatives)."""

    def __init__(self, names: list[str], rounds: int = 20, rate: float = 0.4, ridge: float = 1.0):
        self.names, self.rounds, self.rate, self.ridge, self.trees, self.start = names, rounds, rate, ridge, [], 0.0

    def _split(self, cells, rows):
        best = (0.0, None)
        g_all, h_all = sum(r[1] for r in rows), sum(r[2] for r in rows)
        for f in range(len(self.names)):
            by: dict[int, list[float]] = {}
            for i, g, h in rows:
                at = by.setdefault(cells[i][0][f], [0.0, 0.0])
                at[0] += g
                at[1] += h
            g = h = 0.0
            for value in sorted(by)[:-1]:
                g, h = g + by[value][0], h + by[value][1]
                gain = g * g / (h + self.ridge) + (g_all - g) ** 2 / (h_all - h + self.ridge) - g_all**2 / (h_all + self.ridge)
                if gain > best[0] + 1e-9:
                    best = (gain, (f, value))
        return best[1]

    def _leaf(self, rows) -> float:
        return self.rate * sum(r[1] for r in rows) / (sum(r[2] for r in rows) + self.ridge)

    def _grow(self, cells, rows, depth):
        cut = self._split(cells, rows) if depth else None
        if cut is None:
            return self._leaf(rows)
        f, v = cut
        return (f, v, self._grow(cells, [r for r in rows if cells[r[0]][0][f] <= v], depth - 1), self._grow(cells, [r for r in rows if cells[r[0]][0][f] > v], depth - 1))

    def fit(self, cells: list[tuple[tuple[int, ...], float, float]]) -> Trees:
        pos, neg = sum(c[1] for c in cells), sum(c[2] for c in cells)
        self.start = math.log((pos + 1) / (neg + 1))
        score = [self.start] * len(cells)
        for _ in range(self.rounds):
            rows = []
            for i, (_, p, n) in enumerate(cells):
                q = 1 / (1 + math.exp(-score[i]))
                rows.append((i, p * (1 - q) - n * q, (p + n) * q * (1 - q)))
            tree = self._grow(cells, rows, 2)
            self.trees.append(tree)
            for i, c in enumerate(cells):
                score[i] += self._value(tree, c[0])
        return self

    def _value(self, tree, x) -> float:
        while isinstance(tree, tuple):
            tree = tree[2] if x[tree[0]] <= tree[1] else tree[3]
        return tree

    def score(self, x) -> float:
        out = self.start
        for t in self.trees:  # added in the order of ``expression``: thresholds are met exactly
            out += self._value(t, x)
        return out

    def expression(self, made: dict[str, Column]) -> Column:
        def one(tree) -> Column:
            if not isinstance(tree, tuple):
                return F.lit(float(tree))
            return F.when(made[self.names[tree[0]]] <= tree[1], one(tree[2])).otherwise(one(tree[3]))

        out = F.lit(float(self.start))
        for t in self.trees:
            out = out + one(t)
        return out


def threshold(trees: Trees, cells: list[tuple[tuple[int, ...], float, float]], precision: float) -> float:
    """The least score from which the other half's candidates reach the precision; infinite if none does. Equal scores are one step."""
    by: dict[float, list[float]] = {}
    for x, p, n in cells:
        at = by.setdefault(trees.score(x), [0.0, 0.0])
        at[0] += p
        at[1] += n
    at, hits, misses = math.inf, 0.0, 0.0
    for score in sorted(by, reverse=True):
        hits, misses = hits + by[score][0], misses + by[score][1]
        if hits >= precision * (hits + misses):
            at = score
    return at


def fit(found: DataFrame, precision: float = 0.95) -> tuple[Trees, list[float]]:
    """Trees and one threshold per kind: from the wide candidates of the kind in the half that didn't teach, else from
    all of the kind, else the score whose chance is the precision."""
    names = list(FEATURES)
    rows = found.select("fold", F.explode(F.concat("base", "wide")).alias("x"))
    made = features(F.col("x"))
    cells = rows.select("fold", F.col("x.ok").alias("ok"), *[made[n].alias(n) for n in names]).groupBy("fold", "ok", *names).count().collect()
    halves: list[dict] = [{}, {}]
    for c in cells:
        at = halves[int(c["fold"])].setdefault(tuple(c[n] for n in names), [0.0, 0.0])
        at[0 if c["ok"] else 1] += c["count"]
    fold0, fold1 = ([(x, p, n) for x, (p, n) in sorted(h.items())] for h in halves)
    trees = Trees(names).fit(fold0)
    least = []
    for kind in range(len(KINDS)):
        own = [c for c in fold1 if c[0][0] == kind]
        own = [c for c in own if c[0][1] == 1] or own
        both = sum(c[1] for c in own) and sum(c[2] for c in own)
        least.append(threshold(trees, own, precision) if both else math.log(precision / (1 - precision)))
    return trees, least


def find_pii(docs: DataFrame, precision: float = 0.95, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, base, added: arrays of spans (kind index, s, e, hit, ...), each by kind and start."""
    found = stored(proposals(docs, key, text), "proposals")
    trees, least = fit(found, precision)
    bare = lambda spans: F.transform(spans, lambda b: b.dropFields("ok"))
    bars = F.array(*[F.lit(x) for x in least])
    made = lambda w: F.array(F.struct(*[c.alias(n) for n, c in features(w).items()]))  # noqa: E731  in an array of one: each feature is made once
    score = lambda w: F.transform(made(w), lambda x: trees.expression({n: x[n] for n in FEATURES}))[0]
    scored = F.filter("wide", lambda w: score(w) >= bars[w["kind"]])
    return found.select("doc_id", bare(F.filter("base", lambda b: b["ok"])).alias("base"), bare(scored).alias("added"))


def spelled(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    kinds = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", kinds[x["kind"]], x["s"], x["e"])), ",")


def _highest(values: Column) -> Column:
    """The greatest value up to each place of a short array."""
    return F.aggregate(values, F.array().cast("array<int>"), lambda a, x: F.concat(a, F.array(F.greatest(x, F.coalesce(F.try_element_at(a, F.lit(-1)), x)))))


def _bound(value: Column, then) -> Column:
    """``then`` of a value that is made once: what a function of elements names otherwise is made anew for every element."""
    return F.transform(F.array(value), then)[0]


def redact(text: Column, spans: Column) -> Column:
    """The text with each span replaced by its kind in brackets; what overlaps is one span, of the first one's kind. Null spans or text change nothing."""
    kinds = F.array(*[F.lit(k) for k in KINDS])
    ordered = F.array_sort(F.transform(spans, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["kind"].alias("kind"))))

    def chunked(x):
        n = F.ceil(F.size(x) / CHUNK).cast("int")
        return F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), n - 1)), lambda c: _highest(F.transform(F.slice(x, c * CHUNK + 1, F.lit(CHUNK)), lambda y: y["e"])))

    def joined(parts):  # the furthest end up to each span
        return _bound(F.concat(F.array(F.lit(0)), _highest(F.transform(parts, lambda c: F.element_at(c, -1)))), lambda before: F.flatten(F.transform(parts, lambda c, i: F.transform(c, lambda x: F.greatest(x, before[i])))))

    def put(x, upto, chars):
        piece = lambda y, i: F.when(y["s"] >= upto[i], F.concat(F.array_join(F.slice(chars, upto[i] + 1, y["s"] - upto[i]), ""), F.lit("["), kinds[y["kind"]], F.lit("]"))).otherwise("")
        end = upto[F.size(x)]
        return F.concat(F.array_join(F.transform(x, piece), ""), F.array_join(F.slice(chars, end + 1, F.greatest(F.size(chars) - end, F.lit(0))), ""))

    whole = _bound(ordered, lambda x: _bound(F.concat(F.array(F.lit(0)), _bound(chunked(x), joined)), lambda upto: _bound(F.split(text, ""), lambda chars: put(x, upto, chars))))
    return F.when((F.size(spans) > 0) & (F.char_length(text) > 0), whole).otherwise(text)
