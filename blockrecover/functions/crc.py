"""CRC-32 algebra as native expressions.

Appending t zero bytes to a message acts on its remainder as a linear map over GF(2). With S(t) for that map on
conditioned checksums, crc(A + B) = S(len B)(crc A) xor crc(B). Maps are 32 columns of 32 bits; S(2**i bytes) for i = 0..30
are precomputed from the polynomial by squaring, so a shift by a column's value is at most one matrix product per set
bit. Inverse maps undo a suffix and turn a target checksum into the one a missing block must have.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The reflected polynomial (fixed value).
POLYNOMIAL = 0xEDB88320


def apply_map(columns: tuple[int, ...], value: int) -> int:
    out = 0
    for i in range(32):
        if value >> i & 1:
            out ^= columns[i]
    return out


def compose(a: tuple[int, ...], b: tuple[int, ...]) -> tuple[int, ...]:
    """The map that applies b, then a."""
    return tuple(apply_map(a, x) for x in b)


@lru_cache(maxsize=None)
def shift_map(n: int) -> tuple[int, ...]:
    """The map of n appended zero bytes."""
    if n == 0:
        return tuple(1 << i for i in range(32))
    if n == 1:
        bit = tuple([POLYNOMIAL] + [1 << i for i in range(31)])
        for _ in range(3):
            bit = compose(bit, bit)
        return bit
    half = shift_map(n // 2)
    out = compose(half, half)
    return compose(shift_map(1), out) if n & 1 else out


@lru_cache(maxsize=None)
def inverse_map(n: int) -> tuple[int, ...]:
    """The inverse of shift_map(n), by elimination over GF(2)."""
    rows = [sum((shift_map(n)[c] >> r & 1) << c for c in range(32)) for r in range(32)]
    own = [1 << r for r in range(32)]
    for c in range(32):
        p = next(r for r in range(c, 32) if rows[r] >> c & 1)
        rows[c], rows[p], own[c], own[p] = rows[p], rows[c], own[p], own[c]
        for r in range(32):
            if r != c and rows[r] >> c & 1:
                rows[r] ^= rows[c]
                own[r] ^= own[c]
    return tuple(sum((own[r] >> c & 1) << r for r in range(32)) for c in range(32))


def combine(a: int, b: int, length: int) -> int:
    """crc(A + B) of crc(A), crc(B) and the length of B."""
    return apply_map(shift_map(length), a) ^ b


def required(target: int, prefix: int, block: int, suffix: int, suffix_length: int) -> int:
    """The checksum that a missing block of ``block`` bytes must have between prefix and suffix."""
    left = target ^ apply_map(shift_map(block + suffix_length), prefix) ^ suffix
    return apply_map(inverse_map(suffix_length), left)


def _table(columns: tuple[int, ...]) -> str:
    """A map as SQL text: one expression to parse, not a call to the JVM for each number."""
    return "array(" + ", ".join(f"{x}L" for x in columns) + ")"


def _product(columns: tuple[int, ...], value: Column) -> Column:
    table = F.expr(_table(columns))
    picked = F.zip_with(table, F.sequence(F.lit(0), F.lit(31)), lambda c, i: F.when(F.call_function("getbit", value, i) == 1, c).otherwise(F.lit(0).cast("long")))
    return F.when(value.isNotNull(), F.aggregate(picked, F.lit(0).cast("long"), lambda a, x: a.bitwiseXOR(x)))


def shift_by(value: Column, n: int) -> Column:
    """S(n) of a column, n known at planning."""
    return _product(shift_map(n), value)


def unshift_by(value: Column, n: int) -> Column:
    return _product(inverse_map(n), value)


def shift(value: Column, n: Column, *, most: int = 1 << 15, inverse: bool = False) -> Column:
    """S(n) of a column for a column n below ``most`` (a larger one is an error): one conditional product per bit of n, folded
    over a table of maps so that the plan does not grow with the bits."""
    bits = max(1, (most - 1).bit_length())
    maps = F.expr("array(" + ", ".join(_table((inverse_map if inverse else shift_map)(1 << i)) for i in range(bits)) + ")")
    def step(acc, i):
        picked = F.zip_with(F.get(maps, i), F.sequence(F.lit(0), F.lit(31)), lambda c, j: F.when(F.call_function("getbit", acc, j) == 1, c).otherwise(F.lit(0).cast("long")))
        return F.when(F.call_function("getbit", n.cast("long"), i) == 1, F.aggregate(picked, F.lit(0).cast("long"), lambda a, x: a.bitwiseXOR(x))).otherwise(acc)

    fits = F.when(n >= most, F.raise_error(F.lit(f"shift by {most} bytes or more"))).otherwise(value.cast("long"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(bits - 1)), fits, step)


def crc_hex(col: Column) -> Column:
    """Eight lower-case hexadecimal digits of a text's CRC-32."""
    return F.lower(F.lpad(F.hex(F.crc32(col)), 8, "0"))


def check(a: bytes, b: bytes) -> bool:
    return combine(zlib.crc32(a), zlib.crc32(b), len(b)) == zlib.crc32(a + b)
