"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadmax.functions.hashing import INT_MAX, draw, hash31
from spreadmax.operators.graph import CascadeGraph
from spreadmax.operators.sampling import with_sims
from spreadmax.session import written


def draws(g: CascadeGraph, runs: int, seed: int = 7, sampler: str = "xor") -> DataFrame:
    """(src, dst, sim, d): the draw of every edge in every simulation."""
    return with_sims(g.edges.select("src", "dst", "h"), runs, seed).select("src", "dst", "sim", draw("h", "x", sampler).alias("d"))


def draw_cdf(g: CascadeGraph, runs: int, bins: int = 16, seed: int = 7, sampler: str = "xor") -> DataFrame:
    """(bin, n, cdf): the share of draws up to the end of each bin of [0, 1]."""
    width = (INT_MAX + 1) // bins
    counts = draws(g, runs, seed, sampler).groupBy(F.floor(F.col("d") / width).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    upto = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)  # a row per bin
    whole = Window.partitionBy(F.lit(1))
    return counts.select("bin", "n", F.round(F.sum("n").over(upto) / F.sum("n").over(whole), 9).alias("cdf"))


def ks_uniform(cdf: DataFrame, bins: int = 16) -> DataFrame:
    """(ks): the largest distance of the binned distribution from the uniform one."""
    return cdf.agg(F.round(F.max(F.abs(F.col("cdf") - (F.col("bin") + 1) / bins)), 6).alias("ks"))


def distinct_samples(sampled: DataFrame, runs: int) -> DataFrame:
    """(n_distinct): different kept-edge sets among the simulations; empty ones count as one."""
    marks = sampled.groupBy("sim").agg(
        F.bit_xor(F.xxhash64("src", "dst")).alias("a"), F.sum(F.hash("src", "dst").cast("long")).alias("b"), F.count(F.lit(1)).alias("n")
    )
    full = marks.agg(F.countDistinct("a", "b", "n").alias("d"), F.count(F.lit(1)).alias("sims"))
    return full.select((F.col("d") + (F.col("sims") < runs).cast("long")).alias("n_distinct"))


#: Simulations that keep a group of edges, up to which its subsets of simulations are listed.
SUBSET_RUNS = 16


def pair_cokeep(sampled: DataFrame, runs: int, p: float) -> DataFrame:
    """(pairs): edge pairs kept together in at least runs * p / 2 simulations and at least twice.

    No pair of edges is made. Edges that the same simulations keep are one group (`runs`, `c`). A set of simulations
    that n edges have in common lies in n (n - 1) / 2 pairs; by inclusion and exclusion over sets of at least `least`
    simulations every pair with enough of them in common counts once. Sets of a group with many simulations would be
    too many, so pairs with such a group are counted from its common simulations with each other group.
    """
    least = max(2, math.ceil(runs * p / 2))
    kept_by = sampled.groupBy("src", "dst").agg(F.sort_array(F.collect_list("sim")).alias("runs")).filter(F.size("runs") >= least)
    groups = written(kept_by.groupBy("runs").agg(F.count(F.lit(1)).alias("c")), "groups")
    few, many = (groups.filter(x) for x in (F.size("runs") <= SUBSET_RUNS, F.size("runs") > SUBSET_RUNS))
    masks = F.explode(F.expr("sequence(0, shiftleft(1, size(runs)) - 1)"))
    shared = few.select("runs", "c", masks.alias("mask")).filter(F.bit_count("mask") >= least)
    shared = shared.groupBy(F.expr("filter(runs, (x, i) -> (shiftright(mask, i) & 1) = 1)").alias("shared")).agg(F.sum("c").alias("n"))
    signs = F.array(*[F.lit((-1) ** (j - least) * math.comb(j - 1, least - 1)) for j in range(least, max(least, SUBSET_RUNS) + 1)])
    sign = F.get(signs, F.size("shared") - least)
    n = F.col("n").cast("decimal(19,0)")
    total = shared.agg(F.sum((n * (n - 1) / 2).cast("decimal(28,0)") * sign.cast("decimal(10,0)")).alias("pairs"))
    # pairs of groups of which one has many simulations, each pair of groups once; pairs within such a group
    a = many.select(F.col("runs").alias("r1"), F.col("c").alias("c1"))
    b = groups.select(F.col("runs").alias("r2"), F.col("c").alias("c2"))
    once = (F.size("r2") <= SUBSET_RUNS) | (F.col("r1") < F.col("r2"))
    across = a.join(b, once & (F.size(F.array_intersect("r1", "r2")) >= least))
    total = total.unionByName(across.agg(F.sum(F.col("c1").cast("decimal(19,0)") * F.col("c2")).cast("decimal(38,0)").alias("pairs")))
    c = F.col("c").cast("decimal(19,0)")
    total = total.unionByName(many.agg(F.sum((c * (c - 1) / 2).cast("decimal(28,0)")).cast("decimal(38,0)").alias("pairs")))
    return total.agg(F.coalesce(F.sum("pairs"), F.lit(0)).cast("long").alias("pairs"))


def hash_bias(pairs: DataFrame, bits: int = 16) -> DataFrame:
    """(bit, flips, changed) of ids (u, v): for each flipped bit of u, how many of the 31 output bits changed over all rows."""
    known = pairs.filter(F.col("u").isNotNull() & F.col("v").isNotNull())
    rows = known.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).withColumn("bit", F.explode(F.sequence(F.lit(0), F.lit(bits - 1))))
    flipped = F.col("u").bitwiseXOR(F.expr("shiftleft(1L, bit)"))
    changed = F.bit_count(hash31("u", "v").bitwiseXOR(hash31(flipped, "v")))
    return rows.groupBy("bit").agg(F.count(F.lit(1)).alias("flips"), F.sum(changed.cast("long")).alias("changed"))


def timed(run: Callable[[], DataFrame | object]) -> tuple[object, float]:
    """What a method gives, and its seconds."""
    start = time.perf_counter()
    out = run()
    return out, time.perf_counter() - start


def speedup(runs: DataFrame, base: str) -> DataFrame:
    """runs (graph, setting, method, seconds) -> seconds of `base` over those of each method."""
    own = runs.filter(F.col("method") == base).select("graph", "setting", F.col("seconds").alias("base_seconds"))
    return runs.join(own, ["graph", "setting"]).select(
        "graph", "setting", "method", F.round(F.col("base_seconds") / F.col("seconds"), 3).alias("speedup")
    )


def report_cube(runs: DataFrame, value: str = "score") -> DataFrame:
    """Means by graph, setting and method, and over each of them."""
    return runs.cube("graph", "setting", "method").agg(
        F.round(F.avg(value), 4).alias(value), F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level")
    )


def report_pivot(runs: DataFrame, value: str = "score") -> DataFrame:
    """Graphs down, methods and settings across, in the form of the published tables."""
    return runs.withColumn("c", F.concat_ws("_", "method", "setting")).groupBy("graph").pivot("c").agg(F.round(F.first(value), 4))


def jaccard(a: DataFrame, b: DataFrame) -> DataFrame:
    """(common, either, jaccard) of two seed sets."""
    common = a.select("id").intersect(b.select("id")).agg(F.count(F.lit(1)).alias("common"))
    either = a.select("id").union(b.select("id")).distinct().agg(F.count(F.lit(1)).alias("either"))
    return common.crossJoin(either).withColumn("jaccard", F.round(F.col("common") / F.col("either"), 6))  # one row each


def memo_bytes(n: int, runs: int, memo_rows: int) -> dict[str, int]:
    """Bytes of the dense memo (labels and sizes, 4 bytes each) and of the sparse one (28 bytes a row)."""
    return {"dense": 2 * n * runs * 4, "sparse": 28 * memo_rows}


def estimate_bias(self_sigma: float, score: float) -> float:
    """How far a method's own estimate lies above the independent score, as a share."""
    return (self_sigma - score) / score if score else 0.0


def stage_shares(stages: dict[str, float]) -> dict[str, float]:
    """Each stage's share of the total time."""
    total = sum(stages.values()) or 1.0
    return {k: round(v / total, 6) for k, v in stages.items()}


def draw_tiles(drawn: DataFrame, tiles: int, bins: int = 256) -> DataFrame:
    """(tile, n, top): the draws in `tiles` parts of equal number in the order of their value. Ranks come from counts of
    bins of the value and the order within a bin, so no task sees all draws."""
    binned = drawn.withColumn("bin", F.floor(F.col("d") / ((INT_MAX + 1) // bins)).cast("int"))
    counts = binned.groupBy("bin").agg(F.count(F.lit(1)).alias("c"))
    upto = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)  # a row per bin
    begins = counts.select("bin", F.coalesce(F.sum("c").over(upto), F.lit(0)).alias("begin"), F.sum("c").over(Window.partitionBy(F.lit(1))).alias("all"))
    own = Window.partitionBy("bin").orderBy("d", "src", "dst", "sim")
    ranked = binned.join(F.broadcast(begins), "bin").withColumn("rank", F.col("begin") + F.row_number().over(own) - 1)
    size, more = F.expr(f"`all` div {tiles}"), F.col("all") % tiles  # the first tiles are larger by one
    wide = more * (size + 1)
    tile = F.when(F.col("rank") < wide, F.floor(F.col("rank") / (size + 1))).otherwise(more + F.floor((F.col("rank") - wide) / F.greatest(size, F.lit(1))))
    return ranked.groupBy((tile + 1).cast("int").alias("tile")).agg(F.count(F.lit(1)).alias("n"), F.max("d").alias("top"))


def gain_ranks(gains: DataFrame) -> DataFrame:
    """(id, gain_sum, rk, dr): rank and dense rank by gain, from a row per different gain (few) in place of one per vertex."""
    counts = gains.groupBy("gain_sum").agg(F.count(F.lit(1)).alias("c"))
    order = Window.orderBy(F.desc("gain_sum"))
    above = F.coalesce(F.sum("c").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranks = counts.select("gain_sum", (above + 1).cast("int").alias("rk"), F.row_number().over(order).alias("dr"))
    return gains.join(ranks, "gain_sum").select("id", "gain_sum", "rk", "dr")


def approx_ratio(chosen: float, best: float, k: int) -> tuple[float, float, bool]:
    """The ratio of a greedy choice to the optimum, the ratio that is guaranteed, and whether it holds."""
    bound = 1 - (1 - 1 / k) ** k
    ratio = chosen / best if best else 1.0
    return ratio, bound, ratio >= bound - 1e-9


def memory_report(spark: SparkSession) -> DataFrame:
    """(measure, bytes): shuffle and spill over all stages so far, and the largest heap seen of an executor."""
    return spark.createDataFrame(list(memory_now(spark).items()), "measure string, bytes long")


def memory_now(spark: SparkSession) -> dict[str, int]:
    """The same as numbers; a run's own are the differences of two calls."""
    store = spark.sparkContext._jsc.sc().statusStore()
    totals = {"shuffle_write": 0, "spill_disk": 0, "spill_memory": 0, "heap_peak": 0}
    stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
    for i in range(stages.size()):
        stage = stages.apply(i)
        totals["shuffle_write"] += stage.shuffleWriteBytes()
        totals["spill_disk"] += stage.diskBytesSpilled()
        totals["spill_memory"] += stage.memoryBytesSpilled()
    executors = store.executorList(False)
    for i in range(executors.size()):
        peak = executors.apply(i).peakMemoryMetrics()
        if peak.isDefined():
            totals["heap_peak"] = max(totals["heap_peak"], peak.get().getMetricValue("JVMHeapMemory"))
    return totals
