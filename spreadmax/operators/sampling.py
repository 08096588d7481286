"""Sampled edges: fused into the scan, never stored unless asked for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spreadmax.functions.hashing import constant_list, independent_draw, kept
from spreadmax.operators.graph import CascadeGraph

LITERAL_RUNS = 4096
SCORE_SEED = 101


def with_sims(df: DataFrame, runs: int, seed: int = 7, first: int = 0) -> DataFrame:
    """Every row once per simulation, with (sim, x): a map, no join."""
    spark = df.sparkSession
    if runs - first > LITERAL_RUNS:
        raise ValueError("process simulations in waves of at most 4096")
    xs = constant_list(spark, runs, seed)[first:]
    pairs = F.array(*[F.struct(F.lit(first + i).alias("sim"), F.lit(x).alias("x")) for i, x in enumerate(xs)])
    return df.withColumn("s", F.explode(pairs)).select(*df.columns, "s.sim", "s.x")


def fused_sample(
    g: CascadeGraph, runs: int, seed: int = 7, sampler: str = "xor", strict: bool = False, first: int = 0
) -> DataFrame:
    """(sim, src, dst) of kept edges from one scan of the edges, without a shuffle.

    sampler: 'xor', 'remix', or 'independent', whose draws share no hash between simulations.
    """
    rows = with_sims(g.edges.select("src", "dst", "h", "thr"), runs, seed, first)
    return rows.filter(keeps(sampler, strict, seed)).select("sim", "src", "dst")


def keeps(sampler: str = "xor", strict: bool = False, score_seed: int = SCORE_SEED) -> Column:
    """Whether an edge row with (src, dst, h, thr, sim, x) is in the sample."""
    if sampler == "independent":
        d = independent_draw("src", "dst", "sim", score_seed)
        return d < F.col("thr") if strict else d <= F.col("thr")
    return kept("h", "x", "thr", sampler, strict)


def sample_edges(g: CascadeGraph, runs: int, seed: int = SCORE_SEED) -> DataFrame:
    """Independent samples, as a baseline stores them: (sim, src, dst)."""
    sims = F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))
    return g.edges.select("src", "dst", "thr", sims.alias("sim")).filter(keeps("independent", score_seed=seed)).select("sim", "src", "dst")
