"""Check codes of chosen width under a chosen polynomial.

The code is a reflected cyclic redundancy check with all ones before and after. For
digests of fixed length it is affine over GF(2): a constant xor one table entry per
nibble, so a code is 64 lookups in an expression and no bit loop. Codes over 64 bits are
two limbs of a long each.
"""

from __future__ import annotations

import secrets
from functools import lru_cache

from pyspark.sql import Column
from pyspark.sql import functions as F

WIDTHS = [32 + 4 * i for i in range(25)]
#: Fixed value: bits 31, 35, ..., 127, forced in every random polynomial.
FORCED = 0x88888888888888888888888880000000


def condition(r: int) -> int:
    return r | FORCED


def draw() -> int:
    return condition(secrets.randbits(128))


def code(data: bytes, k: int, r: int) -> int:
    """Bit by bit: the definition."""
    ones = (1 << k) - 1
    poly, crc = r & ones, ones
    for byte in data:
        crc ^= byte
        for _ in range(8):
            crc = crc >> 1 ^ (poly if crc & 1 else 0)
    return crc ^ ones


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


@lru_cache(64)
def nibble_tables(k: int, r: int, size: int = 32) -> tuple[int, list[int]]:
    """(code of zeros, entry for nibble value v at place p at index 16 p + v)."""
    zero = code(bytes(size), k, r)
    table = []
    for p in range(2 * size):
        bits = []
        for v in (1, 2, 4, 8):
            data = bytearray(size)
            data[p // 2] = v << 4 if p % 2 == 0 else v
            bits.append(code(bytes(data), k, r) ^ zero)
        table += [bits[0] * (v & 1) ^ bits[1] * (v >> 1 & 1) ^ bits[2] * (v >> 2 & 1) ^ bits[3] * (v >> 3) for v in range(16)]
    return zero, table


def _limb(digest_hex: Column, zero: int, table: list[int]) -> Column:
    values = F.lit([_signed(x) for x in table]) if any(table) else None
    if values is None:
        return F.lit(_signed(zero)).cast("long")
    at = lambda p: p * 16 + F.instr(F.lit("0123456789abcdef"), F.substring(digest_hex, p + 1, F.lit(1))) - 1
    return F.aggregate(F.sequence(F.lit(0), F.lit(len(table) // 16 - 1)), F.lit(_signed(zero)).cast("long"), lambda acc, p: acc.bitwiseXOR(values[at(p)]))


def code_columns(digest_hex: Column, k: int, r: int) -> tuple[Column, Column]:
    """(code_hi, code_lo) of a SHA-256 digest in lower-case hex."""
    zero, table = nibble_tables(k, r)
    low = (1 << 64) - 1
    hi = _limb(digest_hex, zero >> 64, [x >> 64 for x in table]) if k > 64 else F.lit(0).cast("long")
    return hi, _limb(digest_hex, zero & low, [x & low for x in table])


def step_is_invertible(k: int, r: int) -> bool:
    """Whether the shift step permutes the k-bit states: true iff the polynomial's top bit is set."""
    return bool(r >> (k - 1) & 1)
