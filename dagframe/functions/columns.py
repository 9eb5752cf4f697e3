"""Column expressions that several operators share."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def stable(x: Column | str, digits: int = 6) -> Column:
    """Rounded for output, without a negative zero."""
    return F.round(F.col(x) if isinstance(x, str) else x, digits) + F.lit(0.0)


def uniform(seed: int, stream: str, *keys: Column) -> Column:
    """A number in (0, 1) that depends on the seed, the stream's name and the keys only: equal in any engine with md5."""
    text = F.concat_ws(":", F.lit(str(seed)), F.lit(stream), *[k.cast("string") for k in keys])
    return (F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") + 0.5) / F.lit(4294967296.0)


def normal(seed: int, stream: str, *keys: Column) -> Column:
    """Standard normal by two uniforms."""
    return F.sqrt(-2 * F.log(uniform(seed, stream + "a", *keys))) * F.cos(2 * math.pi * uniform(seed, stream + "b", *keys))


#: A published five-term rational approximation of the normal tail (absolute error below 7.5e-8).
TAIL = (0.319381530, -0.356563782, 1.781477937, -1.821255978, 1.330274429)
TAIL_SCALE = 0.2316419


def normal_tail(z: Column) -> Column:
    """P(Z >= z) for a standard normal Z."""
    t = 1 / (1 + TAIL_SCALE * F.abs(z))
    poly = F.lit(0.0)
    for c in reversed(TAIL):
        poly = (poly + c) * t
    upper = F.exp(-z * z / 2) / math.sqrt(2 * math.pi) * poly
    return F.when(z >= 0, upper).otherwise(1 - upper)


def normal_tail_sql(z: str) -> str:
    t = f"(1 / (1 + {TAIL_SCALE} * abs({z})))"
    poly = "0.0"
    for c in reversed(TAIL):
        poly = f"({poly} + ({c})) * {t}"
    upper = f"(exp(-({z}) * ({z}) / 2) / {math.sqrt(2 * math.pi)!r} * ({poly}))"
    return f"(CASE WHEN ({z}) >= 0 THEN {upper} ELSE 1 - {upper} END)"


def uniform_sql(seed: int, stream: str, *keys: str) -> str:
    text = " || ':' || ".join([f"'{seed}'", f"'{stream}'", *[f"({k})::VARCHAR" for k in keys]])
    return f"((('0x' || substr(md5({text}), 1, 8))::BIGINT::DOUBLE + 0.5) / 4294967296.0)"


def normal_sql(seed: int, stream: str, *keys: str) -> str:
    return f"(sqrt(-2 * ln({uniform_sql(seed, stream + 'a', *keys)})) * cos(2 * {math.pi!r} * {uniform_sql(seed, stream + 'b', *keys)}))"
