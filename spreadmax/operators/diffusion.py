"""Diffusion models and spread estimators: frontier joins keyed by simulation.

Draws are hashes of (edge, simulation, seed), so a retried task repeats them and
results do not depend on partitions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spreadmax.functions.hashing import INT_MAX, hash31, kept, sim_constants
from spreadmax.operators.graph import CascadeGraph, degrees, symmetrise
from spreadmax.operators.sampling import SCORE_SEED, sample_edges
from spreadmax.session import written


def reach_loop(arcs: DataFrame, starts: DataFrame, keys: list[str], keep: Column) -> DataFrame:
    """(keys..., id, round): what is reached from `starts` (keys..., id) over arcs (u, v, ...) that `keep` keeps.

    A vertex is expanded once, in the round after it was reached. `keep` sees the
    keys and the columns of the arc. `keys` may carry columns that depend on the
    simulation alone.
    """
    found = written(starts.select(*keys, "id").distinct().withColumn("round", F.lit(0)), "reach")
    frontier, n = found, 0
    while True:
        n += 1
        step = (
            frontier.select(*keys, F.col("id").alias("u")).join(arcs, "u").filter(keep).select(*keys, F.col("v").alias("id")).distinct()
        )
        fresh = written(step.join(found, [*keys, "id"], "left_anti").withColumn("round", F.lit(n)), "reach")
        if not fresh.limit(1).count():
            return found
        found, frontier = found.unionByName(fresh), fresh


def _starts(seeds: DataFrame, runs: int) -> DataFrame:
    return seeds.select("id", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("sim"))


def _independent(seed: int) -> Column:
    return hash31(F.least("u", "v"), F.greatest("u", "v"), "sim", seed) <= F.col("thr")


def cascade_rounds(g: CascadeGraph, seeds: DataFrame, runs: int, seed: int = SCORE_SEED) -> DataFrame:
    """Independent cascade round by round: (sim, id, round)."""
    return reach_loop(g.arcs.select("u", "v", "thr"), _starts(seeds, runs), ["sim"], _independent(seed))


def reach_fixed_draws(g: CascadeGraph, seeds: DataFrame, runs: int, seed: int = 7, sampler: str = "xor") -> DataFrame:
    """Reach on the hash draws of the proposed method: (sim, id, round)."""
    sims = F.broadcast(sim_constants(g.edges.sparkSession, runs, seed))
    starts = _starts(seeds, runs).join(sims, "sim")
    return reach_loop(g.arcs.select("u", "v", "h", "thr"), starts, ["sim", "x"], kept("h", "x", "thr", sampler)).drop("x")


def cascade_weighted(edges: DataFrame, seeds: DataFrame, runs: int, seed: int = SCORE_SEED) -> DataFrame:
    """Weighted cascade: each arc into v is used with probability 1 / degree(v), each direction by itself."""
    d = degrees(edges).select(F.col("id").alias("v"), F.col("deg").alias("d"))
    arcs = symmetrise(edges.select("src", "dst")).join(d, "v").select("u", "v", "d")
    keep = hash31("u", "v", "sim", seed).cast("long") * F.col("d") <= INT_MAX
    return reach_loop(arcs, _starts(seeds, runs), ["sim"], keep)


def linear_threshold(edges: DataFrame, seeds: DataFrame, runs: int, seed: int = SCORE_SEED) -> DataFrame:
    """Linear threshold with in-weights 1 / degree: (sim, id, round); v turns active when its active share exceeds its threshold."""
    d = degrees(edges).select(F.col("id").alias("v"), F.col("deg").alias("d"))
    arcs = written(symmetrise(edges.select("src", "dst")).join(d, "v").select("u", "v", "d"), "arcs")
    active = written(_starts(seeds, runs).select("sim", "id").distinct().withColumn("round", F.lit(0)), "active")
    pressed: DataFrame | None = None  # (sim, v, d, n): active neighbours so far
    fresh, n = active, 0
    while True:
        n += 1
        new = fresh.select("sim", F.col("id").alias("u")).join(arcs, "u").groupBy("sim", "v", "d").agg(F.count(F.lit(1)).alias("n"))
        pressed = new if pressed is None else pressed.unionByName(new).groupBy("sim", "v", "d").agg(F.sum("n").alias("n"))
        pressed = written(pressed, "pressed")
        turned = pressed.filter(F.col("n") * INT_MAX > hash31("v", "sim", seed).cast("long") * F.col("d"))
        fresh = written(
            turned.select("sim", F.col("v").alias("id")).join(active, ["sim", "id"], "left_anti").withColumn("round", F.lit(n)), "active"
        )
        if not fresh.limit(1).count():
            return active
        active = active.unionByName(fresh)


def sample_lt(edges: DataFrame, runs: int, seed: int = SCORE_SEED) -> DataFrame:
    """The live-edge form: in each simulation every vertex keeps the in-arc whose interval holds its draw: (sim, u, v)."""
    d = degrees(edges).select(F.col("id").alias("v"), F.col("deg").alias("d"))
    order = Window.partitionBy("v").orderBy("u")
    arcs = symmetrise(edges.select("src", "dst")).join(d, "v").withColumn("k", F.row_number().over(order))
    rows = arcs.withColumn("sim", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
    at = hash31("v", "sim", seed).cast("long") * F.col("d")
    return rows.filter((at >= (F.col("k") - 1) * (INT_MAX + 1)) & (at < F.col("k") * (INT_MAX + 1))).select("sim", "u", "v")


def cascade_live_edges(edges: DataFrame, seeds: DataFrame, runs: int, seed: int = SCORE_SEED) -> DataFrame:
    picked = written(sample_lt(edges, runs, seed).withColumnRenamed("sim", "s"), "picked")
    return reach_loop(picked, _starts(seeds, runs), ["sim"], F.col("s") == F.col("sim"))


def reached_per_sim(reached: DataFrame) -> DataFrame:
    return reached.groupBy("sim").agg(F.count(F.lit(1)).alias("reached"))


def spread_mc(g: CascadeGraph, seeds: DataFrame, runs: int, model: str = "ic", seed: int = SCORE_SEED) -> DataFrame:
    """(sim, reached) of a seed set on fresh samples. model: ic, wc, lt, lt_live."""
    found = {
        "ic": lambda: cascade_rounds(g, seeds, runs, seed),
        "wc": lambda: cascade_weighted(g.edges, seeds, runs, seed),
        "lt": lambda: linear_threshold(g.edges, seeds, runs, seed),
        "lt_live": lambda: cascade_live_edges(g.edges, seeds, runs, seed),
    }[model]()
    return reached_per_sim(found)


def components_of(sampled: DataFrame, runs: int) -> DataFrame:
    """The memo of a stored sample, one task for each simulation where such a task can hold it."""
    from spreadmax.operators.components import components_local, components_star
    from spreadmax.plans.planner import fits_task

    return (components_local if fits_task(sampled, runs) else components_star)(sampled)


def reached_by_components(g: CascadeGraph, seeds: DataFrame, runs: int, seed: int = SCORE_SEED) -> DataFrame:
    """(sim, reached) on the same draws as `cascade_rounds`, without rounds: in an undirected graph seeds reach
    the components of a sample that hold one of them. `seeds` are broadcast: they are few."""
    own = F.broadcast(seeds.select("id").distinct())
    sampled = written(sample_edges(g, runs, seed), "sampled")
    memo = written(components_of(sampled, runs), "memo")
    held = memo.join(own, "id", "left_semi")
    touched = F.broadcast(held.select("sim", "label").distinct())  # at most seeds x runs rows
    inside = memo.join(touched, ["sim", "label"], "left_semi").groupBy("sim").agg(F.count(F.lit(1)).alias("n"))
    hits = held.groupBy("sim").agg(F.count(F.lit(1)).alias("hits"))
    sims = g.edges.sparkSession.range(runs).select(F.col("id").cast("int").alias("sim"))
    alone = seeds.select("id").distinct().count()
    total = alone - F.coalesce("hits", F.lit(0)) + F.coalesce("n", F.lit(0))  # a seed without a kept edge reaches itself
    return sims.join(hits, "sim", "left").join(inside, "sim", "left").select("sim", total.alias("reached"))


def score_seeds(g: CascadeGraph, seeds: DataFrame, runs: int = 1000, seed: int = SCORE_SEED, by: str = "components") -> DataFrame:
    """(sigma, se): the independent score that all methods are judged by. by: 'components', or 'rounds' of a cascade; both agree."""
    if by == "components":
        per_sim = reached_by_components(g, seeds, runs, seed).filter("reached > 0")
    else:
        per_sim = spread_mc(g, seeds, runs, "ic", seed)
    return per_sim.agg(
        F.round(F.avg("reached"), 6).alias("sigma"), F.round(F.stddev_samp("reached") / F.sqrt(F.lit(float(runs))), 6).alias("se")
    )


def forest_exact(edges: DataFrame, level_of, p: float) -> DataFrame:
    """(id, sigma): exact spread of single seeds on a forest whose levels `level_of(id)` gives (parents have the higher level).

    A vertex reaches another with the product of p along their path: sums go up the
    levels and back down, two joins a level, without pairs of vertices.
    """
    links = edges.select(
        F.when(level_of(F.col("src")) < level_of(F.col("dst")), F.col("src")).otherwise(F.col("dst")).alias("id"),
        F.when(level_of(F.col("src")) < level_of(F.col("dst")), F.col("dst")).otherwise(F.col("src")).alias("parent"),
    )
    ids = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    tree = written(ids.join(links, "id", "left").withColumn("level", level_of(F.col("id"))), "tree")
    levels = [r["level"] for r in tree.select("level").distinct().orderBy("level").collect()]
    up = None
    for level in levels:
        own = tree.filter(F.col("level") == level)
        if up is None:
            here = own.withColumn("up", F.lit(1.0))
        else:
            below = up.groupBy(F.col("parent").alias("id")).agg(F.sum("up").alias("below"))
            here = own.join(below, "id", "left").select(
                "id", "parent", "level", (1 + p * F.coalesce("below", F.lit(0.0))).alias("up")
            )
        up = here if up is None else up.unionByName(here)
        up = written(up, "up")
    out = None
    for level in reversed(levels):
        own = up.filter(F.col("level") == level)
        if out is None:
            here = own.select("id", F.col("up").alias("sigma"))
        else:
            above = out.select(F.col("id").alias("parent"), F.col("sigma").alias("above"))
            here = own.join(above, "parent", "left").select(
                "id", F.when(F.col("above").isNull(), F.col("up")).otherwise(F.col("up") + p * (F.col("above") - p * F.col("up"))).alias("sigma")
            )
        out = here if out is None else out.unionByName(here)
    return out.select("id", F.round("sigma", 6).alias("sigma"))


def enumerated_states(edges: DataFrame) -> DataFrame:
    """All 2**m states of a tiny graph: (sim, src, dst) of kept edges and state probabilities (sim, prob), for tests."""
    rows = edges.select("src", "dst", "w").orderBy("src", "dst").collect()
    if len(rows) > 18:
        raise ValueError("only for tiny graphs")
    spark = edges.sparkSession
    states = spark.range(1 << len(rows)).select(F.col("id").alias("sim"))
    prob = F.lit(1.0)
    kept_edges = []
    for k, r in enumerate(rows):
        on = F.shiftright("sim", k).bitwiseAND(1) == 1
        prob = prob * F.when(on, F.lit(r["w"])).otherwise(F.lit(1 - r["w"]))
        kept_edges.append(F.when(on, F.struct(F.lit(r["src"]).alias("src"), F.lit(r["dst"]).alias("dst"))))
    return states.select("sim", prob.alias("prob"), F.array_compact(F.array(*kept_edges)).alias("edges"))


def spread_exact(edges: DataFrame, seed_sets: DataFrame) -> DataFrame:
    """(set, sigma): the exact spread of each (set, id) seed set of a tiny graph."""
    states = written(enumerated_states(edges), "states")
    arcs = states.select("sim", F.explode("edges").alias("e"))
    arcs = arcs.select(F.col("sim").alias("s"), "e.src", "e.dst")
    both = written(symmetrise(arcs), "arcs")
    starts = seed_sets.crossJoin(states.select("sim"))  # a few sets, 2**m states
    reached = reach_loop(both, starts, ["set", "sim"], F.col("s") == F.col("sim"))
    counts = reached.groupBy("set", "sim").agg(F.count(F.lit(1)).alias("n"))
    return counts.join(states.select("sim", "prob"), "sim").groupBy("set").agg(F.round(F.sum(F.col("n") * F.col("prob")), 6).alias("sigma"))


def optimal_seeds(edges: DataFrame, k: int) -> DataFrame:
    """(set, sigma) of the best k-set of a tiny graph; sets are named by their sorted ids."""
    from itertools import combinations

    ids = [r["id"] for r in edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct().orderBy("id").collect()]
    rows = [("-".join(map(str, c)), i) for c in combinations(ids, k) for i in c]
    sets = edges.sparkSession.createDataFrame(rows, "set string, id long")
    return spread_exact(edges, sets).orderBy(F.desc("sigma"), "set").limit(1)
