"""Random numbers that are a pure function of (seed, stream, row id).

A retried task, a second pass over the data and another SQL engine see the same
coin.  Engine ``portable`` takes 13 hex digits of an MD5, which DuckDB can
repeat; engine ``fast`` takes the top 52 bits of xxhash64 and is the default at scale.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

TWO52 = float(1 << 52)


def unit(seed: int, stream: str | Column, row_id: Column, engine: str = "fast") -> Column:
    """Uniform in (0, 1)."""
    stream = F.lit(stream) if isinstance(stream, str) else stream
    if engine == "portable":
        digest = F.md5(F.concat_ws("|", F.lit(str(seed)), stream, row_id.cast("string")))
        bits = F.conv(F.substring(digest, 1, 13), 16, 10).cast("double")
    else:
        bits = F.shiftrightunsigned(F.xxhash64(F.lit(seed), stream, row_id), 12).cast("double")
    return (bits + 0.5) / TWO52


def unit_sql(seed: int, stream: str, row_id: str) -> str:
    """DuckDB text of the portable engine; ``stream`` and ``row_id`` are SQL expressions."""
    return f"((('0x' || substr(md5('{seed}|' || {stream} || '|' || ({row_id})::varchar), 1, 13))::bigint + 0.5) / 4503599627370496.0)"


def cauchy(u: Column) -> Column:
    return F.tan(F.lit(math.pi) * (u - 0.5))


def exponential(u: Column) -> Column:
    return -F.log(u)


def gaussian(u1: Column, u2: Column) -> Column:
    return F.sqrt(-2.0 * F.log(u1)) * F.cos(F.lit(2.0 * math.pi) * u2)


def laplace(u: Column) -> Column:
    v = u - 0.5
    return -F.signum(v) * F.log(1.0 - 2.0 * F.abs(v))


def bucket(u: Column, n: int) -> Column:
    return F.floor(u * n).cast("long")


def poisson_one(u: Column, most: int = 8) -> Column:
    """Poisson(1) count by inversion of one uniform (up to ``most``)."""
    total, term, out = 0.0, math.exp(-1.0), F.lit(most)
    edges = []
    for k in range(most):
        total += term
        edges.append((k, total))
        term /= k + 1
    for k, edge in reversed(edges):
        out = F.when(u < edge, k).otherwise(out)
    return out.cast("int")


def poisson(u: Column, mean: float) -> Column:
    """Poisson count of any mean by inversion of one uniform, up to the last bit of the coin."""
    total, k, edges = 0.0, 0, []
    while k <= mean or 1.0 - total > 0.5 / TWO52:
        step = math.exp(k * math.log(mean) - mean - math.lgamma(k + 1)) if mean > 0 else 1.0
        if k > mean and total + step == total:
            break
        total += step
        edges.append(total)
        k += 1
    return F.size(F.filter(F.array(*[F.lit(e) for e in edges[:-1]]).cast("array<double>"), lambda e: u >= e)).cast("int")


def poisson_one_sql(u: str, most: int = 8) -> str:
    total, term, parts = 0.0, math.exp(-1.0), []
    for k in range(most):
        total += term
        parts.append(f"WHEN {u} < {total!r} THEN {k}")
        term /= k + 1
    return f"CASE {' '.join(parts)} ELSE {most} END"
