"""Portable pseudo-random numbers: 32-bit integer mixing that any SQL engine repeats bit for bit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MASK = 0xFFFFFFFF
FACTOR = 73244475


def _column(x: Column | str | int) -> Column:
    return F.col(x) if isinstance(x, str) else x if isinstance(x, Column) else F.lit(x).cast("long")


def mix32(x: Column | str | int, salt: Column | str | int = 0) -> Column:
    """A 32-bit hash of a BIGINT id and a salt, as BIGINT."""
    x, salt = _column(x).cast("long"), _column(salt).cast("long")
    v = (x.bitwiseXOR(F.shiftright(x, 32)).bitwiseAND(F.lit(MASK)) + salt).bitwiseAND(F.lit(MASK))
    for _ in range(2):
        v = (F.shiftright(v, 16).bitwiseXOR(v) * F.lit(FACTOR)).bitwiseAND(F.lit(MASK))
    return F.shiftright(v, 16).bitwiseXOR(v)


def salt_of(seed: int, use: int, iteration: Column | int = 0, part: Column | int = 0) -> Column:
    """Salt of one use of randomness (coins, ties, admission ...) in one iteration."""
    return F.lit(seed * 7919 + use * 15485863).cast("long") + _column(iteration).cast("long") * 104729 + _column(part).cast("long") * 1299709


def threshold(s: float) -> int:
    """Hashes below it come up with chance ``s``."""
    return int(s * 2**32)


def mix32_text(x: str, salt: str = "0") -> str:
    """The same hash as Spark SQL text, which takes one call to parse."""
    v = f"((({x} ^ shiftright(cast({x} as bigint), 32)) & {MASK}) + {salt} & {MASK})"
    for _ in range(2):
        v = f"((shiftright({v}, 16) ^ {v}) * {FACTOR} & {MASK})"
    return f"(shiftright({v}, 16) ^ {v})"


def salt_text(seed: int, use: int, iteration: int = 0, part: str = "0", turn: str = "0L") -> str:
    """The same salt as Spark SQL text; ``turn`` is a column that adds to the iteration."""
    return f"({seed * 7919 + use * 15485863 + iteration * 104729}L + {turn} * 104729L + cast({part} as bigint) * 1299709L)"


def mix32_sql(x: str, salt: str = "0") -> str:
    """The same hash in DuckDB SQL."""
    v = f"(((xor({x}, ({x}) >> 32) & {MASK}) + ({salt})) & {MASK})"
    for _ in range(2):
        v = f"((xor({v} >> 16, {v}) * {FACTOR}) & {MASK})"
    return f"xor({v} >> 16, {v})"


def salt_sql(seed: int, use: int, iteration: int = 0, part: str = "0") -> str:
    return f"({seed * 7919 + use * 15485863 + iteration * 104729} + ({part})::bigint * 1299709)"


#: Uses of randomness.
PLACE, COIN, TIE, ADMIT, BURN, PICK = range(6)
