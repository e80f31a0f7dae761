"""SQL pieces shared by the queries' SQL: ledgers, features, masks."""

from __future__ import annotations

DAYS = "strftime({}, '%Y-%m-%d')"
LINES = "(SELECT *, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) - 1 AS pos FROM lineitem)"
STAR = f"({LINES} l JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey)"
TABLES = {"E": "(SELECT *, event_id AS pos FROM events)", "O": "(SELECT *, o_orderkey AS pos FROM orders)", "L": LINES, "L14": STAR}
DIMS = {
    "E": {"user_id": "user_id", "event_type": "event_type", "k": "regexp_extract(props, '\"k\": *([0-9]+)', 1)", "day": DAYS.format("ts")},
    "O": {"custkey": "o_custkey", "status": "o_orderstatus", "priority": "o_orderpriority", "orderdate": DAYS.format("o_orderdate")},
    "L": {"suppkey": "l_suppkey", "partkey": "l_partkey", "returnflag": "l_returnflag", "linestatus": "l_linestatus", "quantity": "CAST(l_quantity AS INTEGER)", "shipdate": DAYS.format("l_shipdate")},
    "L14": {
        "from": "o_custkey", "to": "l_suppkey", "to_create": "l_partkey", "from_contract": "c_acctbal < 0", "to_contract": "c_nationkey = s_nationkey", "value": "l_extendedprice", "gas_limit": "CAST(l_quantity AS INTEGER)",
        "gas_price": DAYS.format("l_shipdate"), "gas_used": DAYS.format("o_orderdate"), "function": "p_name", "is_error": "l_returnflag = 'R'", "type": "l_linestatus", "max_fee": "l_discount > 0.05", "max_priority": "l_tax > 0.04",
    },
}


def features(ledger: str, dims: list[str] | None = None, where: str = "true") -> str:
    """A CTE ``pf`` (pos, dim, key)."""
    pairs = {d: e for d, e in DIMS[ledger].items() if dims is None or d in dims}
    src = f"src AS MATERIALIZED (SELECT * FROM {TABLES[ledger]} WHERE {where})"
    return f"{src}, pf AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT CAST(pos AS BIGINT) AS pos, '{d}' AS dim, CAST({e} AS VARCHAR) AS key FROM src WHERE {e} IS NOT NULL" for d, e in pairs.items()) + ")"


def masks(b: int, h: int = 3, pf: str = "pf", name: str = "m") -> str:
    """CTEs of each level and their union ``name`` (level, dim, key, tree, node, mask)."""
    t = b**h
    out = [f"{name}0 AS MATERIALIZED (SELECT dim, key, pos // {t} AS tree, pos // {b} AS node, bit_or(CAST(1 AS BIGINT) << CAST({b - 1} - pos % {b} AS INTEGER)) AS mask FROM {pf} GROUP BY ALL)"]
    for n in range(1, h):
        out.append(f"{name}{n} AS MATERIALIZED (SELECT dim, key, tree, node // {b} AS node, bit_or(CAST(1 AS BIGINT) << CAST({b - 1} - node % {b} AS INTEGER)) AS mask FROM (SELECT dim, key, tree, node, mask FROM {name}{n - 1}) GROUP BY dim, key, tree, node // {b})")
    union = " UNION ALL ".join(f"SELECT {n} AS level, dim, key, tree, node, mask FROM {name}{n}" for n in range(h))
    return ", ".join(out) + f", {name} AS MATERIALIZED ({union})"


def digest(cols: list[str]) -> str:
    return f"sha256(concat_ws('|', {', '.join(f'CAST({c} AS VARCHAR)' for c in cols)}))"


def code(hexcol: str, k: int, r: int) -> str:
    """The check code as an unsigned huge integer, bit by bit."""
    ones = (1 << k) - 1
    poly = r & ones
    u = "UHUGEINT"
    data = f"list_transform(range(0, 32), lambda i: CAST(CAST('0x' || substr({hexcol}, CAST(i * 2 + 1 AS INTEGER), 2) AS INTEGER) AS {u}))"
    steps = f"list_reduce(list_prepend(xor(c, y), list_transform(range(0, 8), lambda z: CAST(0 AS {u}))), lambda a, z: CASE WHEN a & CAST(1 AS {u}) = CAST(1 AS {u}) THEN xor(a >> CAST(1 AS {u}), CAST('{poly}' AS {u})) ELSE a >> CAST(1 AS {u}) END)"
    return f"xor(list_reduce(list_prepend(CAST('{ones}' AS {u}), {data}), lambda c, y: {steps}), CAST('{ones}' AS {u}))"


def limbs(x: str) -> str:
    """code_hi and code_lo of an unsigned huge integer, as signed longs."""
    u, top, whole = "UHUGEINT", 1 << 63, 1 << 64
    signed = lambda e: f"CASE WHEN {e} >= CAST('{top}' AS {u}) THEN CAST(CAST({e} AS HUGEINT) - CAST('{whole}' AS HUGEINT) AS BIGINT) ELSE CAST({e} AS BIGINT) END"
    return f"{signed(f'({x} >> CAST(64 AS {u}))')} AS code_hi, {signed(f'({x} & CAST({chr(39)}{whole - 1}{chr(39)} AS {u}))')} AS code_lo"
