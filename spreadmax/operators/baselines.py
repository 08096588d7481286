"""The greedy baselines that the proposed method is measured against."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadmax.functions.hashing import constant_list, hash31, kept
from spreadmax.operators.components import components_local
from spreadmax.operators.diffusion import components_of, reach_loop
from spreadmax.operators.gains import component_sizes, gains_of, initial_gains, marginal_gains, sized
from spreadmax.operators.graph import CascadeGraph, degrees
from spreadmax.operators.sampling import SCORE_SEED, fused_sample, sample_edges
from spreadmax.operators.selection import Selection, lazy_greedy
from spreadmax.session import release, rewritten, written


def _spreads(g: CascadeGraph, seeds: list[int], candidates: list[int], runs: int, keep, keys: DataFrame) -> dict[int, float]:
    """Mean reach of seeds + {candidate} for each candidate, all in one loop keyed (cand, sim)."""
    spark = g.edges.sparkSession
    rows = [(c, v) for c in candidates for v in (*seeds, c)]
    starts = spark.createDataFrame(rows, "cand long, id long").crossJoin(F.broadcast(keys))  # candidates of one block, runs
    names = ["cand", *keys.columns]
    found = reach_loop(g.arcs.select("u", "v", "h", "thr"), starts, names, keep)
    counts = found.groupBy("cand").agg(F.count(F.lit(1)).alias("n")).collect()  # one row per candidate of the block
    return {r["cand"]: r["n"] / runs for r in counts}


def _sims(g: CascadeGraph, runs: int) -> DataFrame:
    return g.edges.sparkSession.range(runs).select(F.col("id").cast("int").alias("sim"))


def simulated_spreads(g: CascadeGraph, seeds: list[int], runs: int, seed: int = SCORE_SEED) -> DataFrame:
    """(id, gain_sum): the mean reach of seeds + {id} of every vertex that is not a seed, on fresh samples.

    What a vertex reaches in an undirected sample is its component, the same for all its members: each is traversed
    once, not once for each vertex in it. A vertex in a component of a seed adds nothing to what the seeds reach.
    """
    spark = g.edges.sparkSession
    sampled = written(sample_edges(g, runs, seed), "sampled")
    memo = written(components_of(sampled, runs), "memo")
    release(sampled)
    rows = written(sized(memo, component_sizes(memo)), "memo")
    release(memo)
    if not seeds:
        return gains_of(g.vertices, rows, runs).select("id", F.col("gain").alias("gain_sum"))
    own = spark.createDataFrame([(v,) for v in seeds], "id long")
    held = rows.join(F.broadcast(own), "id", "left_semi")
    covered = held.select("sim", "label", "size").distinct()  # at most seeds x runs rows
    reach = covered.agg(F.sum("size").alias("s")).head()["s"] or 0
    base = reach + len(set(seeds)) * runs - held.count()  # a seed without a kept edge reaches itself
    added = marginal_gains(g.vertices, rows, covered.select("sim", "label"), own, runs)
    return added.select("id", ((F.col("gain_sum") + base) / runs).alias("gain_sum"))


def plain_greedy(g: CascadeGraph, k: int, runs: int, seed: int = SCORE_SEED) -> Selection:
    """Every vertex simulated in every round, on fresh samples."""
    out, sigma = Selection(), 0.0
    for r in range(k):
        spreads = written(simulated_spreads(g, [v for v, _ in out.seeds], runs, seed + r), "spreads")
        best = spreads.orderBy(F.desc("gain_sum"), "id").limit(1).collect()
        if not best:
            break
        out.visits += spreads.count()
        release(spreads)
        out.seeds.append((best[0]["id"], round(best[0]["gain_sum"] - sigma, 6)))
        sigma = best[0]["gain_sum"]
    return out


def lazy_forward(g: CascadeGraph, k: int, runs: int, seed: int = SCORE_SEED, lookahead: bool = False, ahead: int = 8) -> Selection:
    """A lazy queue whose first bounds come from simulating every vertex. `lookahead` also simulates a visited
    vertex beside the best one of its round, in the same loop; the seeds are the same, the visits at most as many."""
    first = written(simulated_spreads(g, [], runs, seed), "spreads")
    return _simulated_queue(g, k, runs, seed, first, ahead, Selection(), lookahead)


def _mean_reach(g: CascadeGraph, sets: list[tuple[tuple[int, ...], int]], runs: int) -> list[float]:
    """Mean reach of each (seed set, seed of its draws), all in one loop keyed (cand, sim)."""
    rows = [(c, draw, v) for c, (ids, draw) in enumerate(sets) for v in ids]
    starts = g.edges.sparkSession.createDataFrame(rows, "cand long, draw long, id long").crossJoin(F.broadcast(_sims(g, runs)))  # sets of one block, runs
    keep = hash31(F.least("u", "v"), F.greatest("u", "v"), "sim", F.col("draw")) <= F.col("thr")
    found = reach_loop(g.arcs.select("u", "v", "h", "thr"), starts, ["cand", "draw", "sim"], keep)
    counts = {r["cand"]: r["n"] for r in found.groupBy("cand").agg(F.count(F.lit(1)).alias("n")).collect()}
    return [counts.get(c, 0) / runs for c in range(len(sets))]


def _simulated_queue(
    g: CascadeGraph, k: int, runs: int, seed: int, first: DataFrame, ahead: int, out: Selection, lookahead: bool = False
) -> Selection:
    """The queue with fresh simulations: the draws of a gain depend on the number of seeds it is given, nothing else.

    `first` (id, gain_sum) is fetched in blocks, as far as the queue needs it.
    """
    sigmas: dict[tuple[int, ...], float] = {(): 0.0}

    def gains(wanted: list[tuple[int, ...]]) -> list[float]:
        """Each is a seed set whose last vertex is the candidate."""
        bases = sorted({s[:-1] for s in wanted} - set(sigmas))
        draws = lambda s, given: (s, seed + given)
        reach = _mean_reach(g, [*[draws(s, len(s)) for s in bases], *[draws(s, len(s) - 1) for s in wanted]], runs)
        sigmas.update(zip(bases, reach, strict=False))
        return [round(x - sigmas[s[:-1]], 6) for s, x in zip(wanted, reach[len(bases) :], strict=True)]

    def evaluate(seeds: list[int], stale: list[int]) -> dict[int, float]:
        return dict(zip(stale, gains([(*seeds, v) for v in stale]), strict=True))

    def beside(seeds: list[int], stale: list[int], best: int) -> tuple[dict[int, float], dict[int, float]]:
        both = gains([*[(*seeds, v) for v in stale], *[(*seeds, best, v) for v in stale]])
        return dict(zip(stale, both, strict=False)), dict(zip(stale, both[len(stale) :], strict=True))

    out.seeds, out.visits = lazy_greedy(first, evaluate, k, ahead, beside if lookahead else None)
    release(first)
    return out


def component_greedy(g: CascadeGraph, k: int, runs: int, seed: int = SCORE_SEED) -> Selection:
    """Per round fresh stored samples; a vertex gains the size of its component where no seed is in it."""
    spark, out = g.edges.sparkSession, Selection()
    for r in range(k):
        memo = written(components_local(sample_edges(g, runs, seed + r)), "memo")
        rows = sized(memo, component_sizes(memo))
        if out.seeds:
            own = spark.createDataFrame([(v,) for v, _ in out.seeds], "id long")
            covered = memo.join(F.broadcast(own), "id", "left_semi").select("sim", "label").distinct()
            gains = marginal_gains(g.vertices, rows, covered, own, runs)
        else:
            gains = initial_gains(g.vertices, memo, component_sizes(memo), runs)
        best = gains.orderBy(F.desc("gain_sum"), "id").limit(1).collect()
        release(memo)
        if not best:
            break
        out.seeds.append((best[0]["id"], round(best[0]["gain_sum"] / runs, 6)))
        out.scans += 1
    return out


def hybrid_lazy_greedy(g: CascadeGraph, k: int, runs: int, seed: int = SCORE_SEED, ahead: int = 8) -> Selection:
    """One component round for all first bounds, then the lazy queue with fresh simulations: the sequential baseline."""
    memo = written(components_local(sample_edges(g, runs, seed)), "memo")
    gains = initial_gains(g.vertices, memo, component_sizes(memo), runs)
    first = written(gains.select("id", F.col("gain").alias("gain_sum")), "gains")
    release(memo)
    return _simulated_queue(g, k, runs, seed, first, ahead, Selection())


def fused_greedy(g: CascadeGraph, k: int, runs: int, seed: int = 7, ahead: int = 8) -> Selection:
    """Hash draws in place of stored samples, one simulation after the other, no memo: gains are re-simulated on the same draws."""
    spark = g.edges.sparkSession
    held, total = None, None
    for r in range(runs):  # simulations one by one, as the variant is described
        memo = components_local(fused_sample(g, r + 1, seed, first=r))
        gains = initial_gains(g.vertices, memo, component_sizes(memo), 1).select("id", "gain_sum")
        total = gains if total is None else total.unionByName(gains)
        if r % 8 == 7 or r + 1 == runs:
            held = total = rewritten(held, total.groupBy("id").agg(F.sum("gain_sum").alias("gain_sum")), "total")
    xs = constant_list(spark, runs, seed)
    keys = spark.createDataFrame(list(enumerate(xs)), "sim int, x int")
    sigmas: dict[tuple[int, ...], int] = {}

    def evaluate(seeds: list[int], stale: list[int]) -> dict[int, float]:
        keep = kept("h", "x", "thr")
        key = tuple(seeds)
        if key not in sigmas:
            sigmas[key] = round(_spreads(g, seeds[:-1], seeds[-1:], runs, keep, keys)[seeds[-1]] * runs)
        spread = _spreads(g, seeds, stale, runs, keep, keys)
        return {v: round(spread[v] * runs) - sigmas[key] for v in stale}

    out = Selection()
    out.seeds, out.visits = lazy_greedy(total, evaluate, k, ahead)
    out.seeds = [(v, int(x)) for v, x in out.seeds]
    release(total)
    return out


def degree_seeds(edges: DataFrame, k: int) -> DataFrame:
    """(rank, id, deg): the k vertices of largest degree."""
    top = degrees(edges).orderBy(F.desc("deg"), "id").limit(k)
    return top.select(F.row_number().over(Window.orderBy(F.desc("deg"), "id")).alias("rank"), "id", "deg")  # k rows


def random_seeds(vertices: DataFrame, k: int, seed: int = 5) -> DataFrame:
    """(rank, id): the first k vertices in the order of a seeded hash."""
    h = hash31("id", seed)
    top = vertices.withColumn("r", h).orderBy("r", "id").limit(k)
    return top.select(F.row_number().over(Window.orderBy("r", "id")).alias("rank"), "id")  # k rows
