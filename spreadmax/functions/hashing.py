"""Direction-oblivious edge hashes, draws and thresholds as Column expressions.

All of it stays in generated code. Ids are cast to BIGINT before hashing, since
Spark hashes INT and BIGINT values differently.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

INT_MAX = 2147483647
SAMPLERS = ("xor", "remix", "independent")


def _long(c) -> Column:
    return (F.col(c) if isinstance(c, str) else c if isinstance(c, Column) else F.lit(c)).cast("long")


def hash31(*parts) -> Column:
    """Murmur3 of BIGINT parts, 31 bits."""
    return F.hash(*[_long(p) for p in parts]).bitwiseAND(INT_MAX)


def edge_hash(u="src", v="dst", fn: str = "murmur3") -> Column:
    """One 31-bit hash of an undirected edge: the same for (u, v) and (v, u)."""
    low, high = F.least(_long(u), _long(v)), F.greatest(_long(u), _long(v))
    if fn == "murmur3":
        return hash31(low, high)
    if fn == "xxhash64":
        return F.xxhash64(low, high).bitwiseAND(INT_MAX).cast("int")
    if fn == "md5":
        hexed = F.substring(F.md5(F.concat_ws("-", low.cast("string"), high.cast("string"))), 1, 8)
        return F.conv(hexed, 16, 10).cast("long").bitwiseAND(INT_MAX).cast("int")
    raise ValueError(f"unknown hash {fn}")


def threshold(w) -> Column:
    """Quantised weight; -1 for weights of zero, so that they are never kept."""
    w = F.col(w) if isinstance(w, str) else w
    return F.when(w <= 0, -1).otherwise(F.floor(F.least(w, F.lit(1.0)) * INT_MAX)).cast("int")


def draw(h, x, sampler: str = "xor") -> Column:
    """The draw of an edge in a simulation, 0 .. INT_MAX."""
    h, x = (F.col(c) if isinstance(c, str) else c for c in (h, x))
    if sampler == "xor":
        return h.bitwiseXOR(x)
    if sampler == "remix":
        return hash31(h, x)
    raise ValueError(f"unknown sampler {sampler}")


def kept(h, x, thr="thr", sampler: str = "xor", strict: bool = False) -> Column:
    t = F.col(thr) if isinstance(thr, str) else thr
    d = draw(h, x, sampler)
    return d < t if strict else d <= t


def independent_draw(u, v, sim, seed: int) -> Column:
    """A draw whose every bit is mixed anew for each simulation; for the score oracle."""
    return hash31(u, v, sim, seed)


def constants_of(numbers: DataFrame, seed: int = 7) -> DataFrame:
    """(sim, x): the constant of each simulation number in `numbers` (sim)."""
    return numbers.filter("sim IS NOT NULL").select("sim", hash31(seed, "sim").alias("x"))


def sim_constants(spark: SparkSession, runs: int, seed: int = 7) -> DataFrame:
    """(sim, x): the constant of each simulation."""
    return constants_of(spark.range(runs).select(F.col("id").cast("int").alias("sim")), seed)


def constant_list(spark: SparkSession, runs: int, seed: int = 7) -> list[int]:
    return [r["x"] for r in sim_constants(spark, runs, seed).orderBy("sim").collect()]


def uniform01(*parts) -> Column:
    """A uniform number in [0, 1) from a hash of the parts."""
    return hash31(*parts) / float(INT_MAX + 1)


def normal(mean: float, deviation: float, *parts) -> Column:
    """Box-Muller from two hash uniforms."""
    a = (hash31(*parts, 1) + 1) / float(INT_MAX + 2)
    b = uniform01(*parts, 2)
    return mean + deviation * F.sqrt(-2 * F.ln(a)) * F.cos(2 * math.pi * b)


def register_sql(spark: SparkSession) -> None:
    """edge_hash, draw, kept and threshold for SQL, as temporary functions made of built-ins."""
    for text in (
        f"edge_hash(u BIGINT, v BIGINT) RETURNS INT RETURN hash(least(u, v), greatest(u, v)) & {INT_MAX}",
        "draw(h INT, x INT) RETURNS INT RETURN h ^ x",
        f"threshold(w DOUBLE) RETURNS INT RETURN CASE WHEN w <= 0 THEN -1 ELSE CAST(floor(least(w, 1.0D) * {INT_MAX}) AS INT) END",
        "kept(h INT, x INT, thr INT) RETURNS BOOLEAN RETURN (h ^ x) <= thr",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
