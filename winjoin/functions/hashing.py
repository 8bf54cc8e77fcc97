"""Portable integer hashing as Column expressions, with the same formulas as SQL text for other engines.

Every intermediate stays below 2^63, so ANSI arithmetic never overflows.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MULTIPLIER = 73244475
WORD = 1 << 32


def mix32(x: Column) -> Column:
    """A 32-bit hash of a bigint: two rounds of shift-xor and multiply, and a last shift-xor."""
    x = F.pmod(x.cast("long"), F.lit(WORD))
    for _ in range(2):
        x = (x.bitwiseXOR(F.shiftright(x, 16)) * F.lit(MULTIPLIER)) % F.lit(WORD)
    return x.bitwiseXOR(F.shiftright(x, 16))


def mix32_sql(x: str) -> str:
    x = f"((({x}) % {WORD} + {WORD}) % {WORD})"
    for _ in range(2):
        x = f"((xor({x}, {x} >> 16) * {MULTIPLIER}) % {WORD})"
    return f"xor({x}, {x} >> 16)"


def mix32_int(x: int) -> int:
    """The same on a Python integer."""
    x %= WORD
    for _ in range(2):
        x = (x ^ (x >> 16)) * MULTIPLIER % WORD
    return x ^ (x >> 16)


def key_hash(key: Column, kind: str = "bigint") -> Column:
    """mix32 of an integral key; keys of other types enter by their 64-bit hash (equality is still tested on the key)."""
    return mix32(key if kind in ("bigint", "int", "smallint", "tinyint") else F.xxhash64(key))


def partition_id(key: Column, n_part: int, kind: str = "bigint") -> Column:
    """The partition of a key: from the high half of its hash, so that the low bits stay free for splitting."""
    return (F.shiftright(key_hash(key, kind), 16) % n_part).cast("int")


def partition_id_sql(key: str, n_part: int) -> str:
    return f"CAST(({mix32_sql(key)} >> 16) % {n_part} AS INTEGER)"


def mini_bits(key: Column, depth: int, kind: str = "bigint") -> Column:
    """The low ``depth`` bits of a key's hash."""
    return (key_hash(key, kind) % (1 << depth)).cast("int")


def mini_bits_sql(key: str, depth: int) -> str:
    return f"CAST({mix32_sql(key)} % {1 << depth} AS INTEGER)"


def reversed_bits(value: Column, depth: int) -> Column:
    """The low ``depth`` bits in opposite order: buckets of a directory then own neighbouring slots."""
    out = F.lit(0)
    for i in range(depth):
        out = out + F.shiftleft(F.shiftright(value, i) % 2, depth - 1 - i)
    return out.cast("int")


def reversed_bits_sql(value: str, depth: int) -> str:
    return "CAST(" + (" + ".join(f"(((({value}) >> {i}) % 2) << {depth - 1 - i})" for i in range(depth)) or "0") + " AS INTEGER)"


def reversed_bits_int(value: int, depth: int) -> int:
    return sum((value >> i & 1) << (depth - 1 - i) for i in range(depth))


def floor_div(x: Column, width: int) -> Column:
    """Whole-number division that rounds down, for negative numbers too and exact for all 64 bits."""
    return F.call_function("div", x - F.pmod(x, F.lit(width)), F.lit(width))


def two_to(n: Column) -> Column:
    """2 to the power of a small integer column."""
    return F.call_function("shiftleft", F.lit(1), n.cast("int"))


def buddy_slot(first: Column, local_depth: Column, depth: int) -> Column:
    """First slot of a bucket's buddy in bit-reversed order; null where the bucket has none (local depth 0)."""
    width = two_to(F.lit(depth) - local_depth)
    return F.when(local_depth > 0, F.when((first / width).cast("long") % 2 == 0, first + width).otherwise(first - width)).cast("int")


def uniform(x: Column) -> Column:
    """A number within (0, 1) from a hash."""
    return (mix32(x) + F.lit(0.5)) / F.lit(float(WORD))


def bmodel_key(ident: Column, b: float = 0.7, levels: int = 24, domain: int = 10_000_001, seed: int = 0) -> Column:
    """A key of the b-model: each level takes the upper half with probability b; scaled to the domain."""
    bound = int(b * WORD)
    base = (ident.cast("long") + F.lit(seed)) * 32
    x = F.aggregate(F.sequence(F.lit(0), F.lit(levels - 1)), F.lit(0).cast("long"), lambda acc, j: acc * 2 + F.when(mix32(base + j) < bound, 1).otherwise(0))
    return F.floor((x * domain) / F.lit(1 << levels)).cast("long") if domain * (1 << levels) >= 1 << 62 else F.shiftright(x * domain, levels)


def bmodel_key_sql(ident: str, b: float = 0.7, levels: int = 24, domain: int = 10_000_001, seed: int = 0) -> str:
    bits = " + ".join(f"(CASE WHEN {mix32_sql(f'({ident} + {seed}) * 32 + {j}')} < {int(b * WORD)} THEN {1 << (levels - 1 - j)} ELSE 0 END)" for j in range(levels))
    return f"((CAST({bits} AS BIGINT) * {domain}) >> {levels})"
