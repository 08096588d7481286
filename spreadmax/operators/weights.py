"""Edge-weight settings as Columns over (src, dst, mult): deterministic per edge."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spreadmax.functions.hashing import normal, uniform01
from spreadmax.operators.graph import degrees, symmetrise

WEIGHT_SEED = 11


def constant(p: float) -> Column:
    return F.lit(float(p))


def uniform(low: float = 0.0, high: float = 0.1, seed: int = WEIGHT_SEED) -> Column:
    return low + (high - low) * uniform01("src", "dst", seed)


def gaussian(mean: float = 0.05, deviation: float = 0.025, seed: int = WEIGHT_SEED) -> Column:
    """Normal weights, clamped to [0, 1]."""
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), normal(mean, deviation, "src", "dst", seed)))


def strength(p: float) -> Column:
    """1 - (1 - p) ** mult: every repeated interaction is a chance of its own."""
    return 1 - F.pow(F.lit(1 - p), F.col("mult"))



def settings() -> dict[str, Column]:
    """The four settings of the experiments."""
    return {"c001": constant(0.01), "c01": constant(0.1), "uniform": uniform(), "normal": gaussian()}


def weighted_cascade(edges: DataFrame) -> DataFrame:
    """Directed arcs (u, v, w, d) with w = 1 / degree of the target."""
    d = degrees(edges).select(F.col("id").alias("v"), F.col("deg").alias("d"))
    return symmetrise(edges.select("src", "dst")).join(d, "v").select("u", "v", (1 / F.col("d")).alias("w"), "d")
