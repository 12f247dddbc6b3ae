"""Column expressions that the methods share."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Multipliers below 2**31 keep products of 32-bit values inside a long, here and in SQL.
MIX = (1540483477, 1274126177, 668265263)
MASK = 4294967295


def vertex(key: Column, kind: int) -> Column:
    """Vertex id of a key of one kind; ids of different kinds never meet."""
    return key.cast("long") * 16 + kind


def hash_machine(src: Column, dst: Column, p: int) -> Column:
    """Arithmetic hash placement of an edge on p machines."""
    return ((src * 1000003 + dst * 7919) % 2147483647 % p).cast("int")


def mixed(x: Column, salt: int) -> Column:
    """A well-mixed 32-bit value of a non-negative integer."""
    x = (x * MIX[0] + salt * 97531).bitwiseAND(F.lit(MASK))
    x = (x.bitwiseXOR(F.shiftright(x, 15)) * MIX[1]).bitwiseAND(F.lit(MASK))
    x = (x.bitwiseXOR(F.shiftright(x, 13)) * MIX[2]).bitwiseAND(F.lit(MASK))
    return x.bitwiseXOR(F.shiftright(x, 16))


def mixed_sql(x: str, salt: int) -> str:
    """The same in DuckDB's SQL."""
    a = f"((({x})::BIGINT * {MIX[0]} + {salt * 97531}) & {MASK})"
    b = f"((xor({a}, {a} >> 15) * {MIX[1]}) & {MASK})"
    return f"(select xor(c, c >> 16) from (select (xor(b, b >> 13) * {MIX[2]}) & {MASK} as c from (select {b} as b)))"


def priority(outside: Column, degree: Column, border: Column, alpha: float, beta: float) -> Column:
    """Growth priority of a frontier vertex, least first: few neighbours outside the
    covered set, many inside, and a bonus for vertices that other machines hold already."""
    return (1 + alpha) * outside - (alpha + F.when(border, F.lit(beta)).otherwise(F.lit(0.0))) * degree


def level_share(costs: Column, total: Column) -> Column:
    return F.when(total == 0, F.lit(0.0)).otherwise(costs / total)
