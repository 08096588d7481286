"""Components of many simulations: lanes, sparse rows, contraction, or one simulation per task.

All strategies give the memo (sim, id, label): the vertices that have a kept
edge in a simulation, labelled by the smallest id of their component. Vertices
without a kept edge are components of their own and are implied.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadmax.functions.hashing import constant_list, draw
from spreadmax.operators.connectivity import contracted_components
from spreadmax.operators.graph import CascadeGraph
from spreadmax.operators.sampling import fused_sample
from spreadmax.session import bucketed, release, rewritten, written

PUSHES = ("live", "all", "pull", "auto")
#: 'auto' sends from all vertices as long as live ones have this share of the arcs: choosing arcs then costs more than it saves.
DENSE_SHARE = 0.3


@dataclass
class Trace:
    """What each round of a propagation did."""

    rounds: list[dict] = field(default_factory=list)


def batch_table(spark, runs: int, width: int, seed: int) -> DataFrame:
    """(batch, x0 .. x{width-1}): the constants of each batch; null beyond the last simulation, which no draw can pass."""
    xs = constant_list(spark, runs, seed)
    rows = []
    for b in range(-(-runs // width)):
        own = xs[b * width : (b + 1) * width]
        cells = [str(x) for x in own] + ["CAST(NULL AS INT)"] * (width - len(own))
        rows.append(f"({b}, {', '.join(cells)})")
    names = ", ".join(["batch", *[f"x{j}" for j in range(width)]])
    return spark.sql(f"SELECT * FROM VALUES {', '.join(rows)} AS t({names})")


def lanes_init(g: CascadeGraph, batches: DataFrame, width: int) -> DataFrame:
    """(id, batch, l0 ..): every vertex is labelled by itself in every lane."""
    numbers = F.explode(F.array(*[F.lit(r["batch"]) for r in batches.select("batch").collect()]))
    return g.vertices.select("id", numbers.alias("batch")).select("id", "batch", *[F.col("id").alias(f"l{j}") for j in range(width)])


def lane_messages(lanes: DataFrame, arcs: DataFrame, batches: DataFrame, width: int, sampler: str = "xor") -> DataFrame:
    """(id, batch, m0 ..): the smallest label that reaches each vertex over an arc kept in that lane.

    One join and one code-generated aggregate serve `width` simulations; the
    partial minimum before the shuffle bounds the messages of a task by its targets.
    """
    sides = lanes.withColumnRenamed("id", "u").join(F.broadcast(batches), "batch").join(arcs, "u")
    least = [
        F.min(F.when(draw("h", f"x{j}", sampler) <= F.col("thr"), F.col(f"l{j}"))).alias(f"m{j}") for j in range(width)
    ]
    return sides.groupBy(F.col("v").alias("id"), "batch").agg(*least)


def lane_merge(lanes: DataFrame, messages: DataFrame, width: int) -> DataFrame:
    """New lanes with `live`: whether any label of the vertex became smaller."""
    both = lanes.join(messages, ["id", "batch"], "left")
    new = [F.least(F.col(f"l{j}"), F.col(f"m{j}")) for j in range(width)]
    live = F.lit(False)
    for j in range(width):
        live = live | F.coalesce(F.col(f"m{j}") < F.col(f"l{j}"), F.lit(False))
    return both.select("id", "batch", *[n.alias(f"l{j}") for j, n in enumerate(new)], live.alias("live"))


def components_lanes(
    g: CascadeGraph, runs: int, width: int = 8, seed: int = 7, push: str = "live", sampler: str = "xor", trace: Trace | None = None
) -> DataFrame:
    """Batched label propagation. push: 'live' sends from changed vertices, 'all' from every vertex,
    'pull' lets vertices beside changed ones read all their neighbours, 'auto' takes 'all' in rounds whose
    live vertices have many arcs and 'live' in the others."""
    if push not in PUSHES:
        raise ValueError(f"push is one of {PUSHES}")
    spark = g.edges.sparkSession
    batches = batch_table(spark, runs, width, seed)
    arcs = bucketed(g.arcs.select("u", "v", "h", "thr"), "u", "arcs")  # every round joins them on u
    columns = [f"l{j}" for j in range(width)]
    lanes = written(lanes_init(g, batches, width).withColumn("live", F.lit(True)), "lanes")
    degree = written(arcs.groupBy("u").agg(F.count(F.lit(1)).alias("deg")), "degree") if push == "auto" else None
    every = arcs.count() if push == "auto" else 0
    n, dense = 0, True
    while True:
        if degree is not None and n:
            sent = lanes.filter("live").select(F.col("id").alias("u")).distinct().join(degree, "u").agg(F.sum("deg")).head()[0]
            dense = (sent or 0) > DENSE_SHARE * every
        if push == "all" or (push == "auto" and dense):
            senders, over = lanes, arcs
        elif push in ("live", "auto"):
            senders, over = lanes.filter("live"), arcs
        else:
            beside = arcs.join(lanes.filter("live").select(F.col("id").alias("u")).distinct(), "u", "left_semi").select("v").distinct()
            senders, over = lanes, arcs.join(beside, "v", "left_semi").select("u", "v", "h", "thr")
        messages = lane_messages(senders.select("id", "batch", *columns), over, batches, width, sampler)
        after = written(lane_merge(lanes.drop("live"), messages, width), "lanes")
        changed = after.filter("live").count()
        if trace is not None:
            visited = senders.select(F.col("id").alias("u")).join(over, "u").count()
            trace.rounds.append({"round": n, "live": changed, "arcs_visited": visited})
        release(lanes)
        lanes, n = after, n + 1
        if not changed:
            break
    release(arcs)
    release(degree)
    flat = F.explode(F.array(*[F.struct((F.col("batch") * width + j).alias("sim"), F.col(f"l{j}").alias("label")) for j in range(width)]))
    memo = lanes.select("id", flat.alias("s")).select("s.sim", "id", "s.label").filter(F.col("sim") < runs)
    return without_singletons(memo)


def without_singletons(memo: DataFrame) -> DataFrame:
    """Drop components of one vertex: those whose label is their only member. Only rows that are their own label
    are joined, so a giant component is no hot key."""
    others = memo.filter("id <> label")
    several = others.select("sim", "label").distinct()
    firsts = memo.filter("id = label").join(several, ["sim", "label"], "left_semi")
    return others.select("sim", "id", "label").unionByName(firsts.select("sim", "id", "label"))


def components_minlabel(sampled: DataFrame) -> DataFrame:
    """Synchronous min-label rounds over stored kept edges: (sim, src, dst) -> memo."""
    arcs = written(
        sampled.select("sim", F.explode(F.array(F.struct(F.col("src").alias("u"), F.col("dst").alias("v")), F.struct(F.col("dst").alias("u"), F.col("src").alias("v")))).alias("a")).select("sim", "a.u", "a.v"),
        "arcs",
    )
    labels = written(arcs.select("sim", F.col("u").alias("id"), F.col("u").alias("label"), F.lit(True).alias("live")).distinct(), "labels")
    while labels.filter("live").limit(1).count():
        sent = labels.filter("live").select("sim", F.col("id").alias("u"), "label")
        least = sent.join(arcs, ["sim", "u"]).groupBy("sim", F.col("v").alias("id")).agg(F.min("label").alias("m"))
        after = labels.join(least, ["sim", "id"], "left").select(
            "sim", "id", F.least("label", "m").alias("label"), F.coalesce(F.col("m") < F.col("label"), F.lit(False)).alias("live")
        )
        labels = rewritten(labels, after, "labels")
    release(arcs)
    return labels.select("sim", "id", "label")


def components_star(sampled: DataFrame) -> DataFrame:
    """Contraction: rounds grow with the logarithm of the diameter, for samples near the critical point."""
    return contracted_components(sampled, by=["sim"])


def hooked(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """The smallest vertex of the component of each of the vertices 0 .. n-1, over edges a - b."""
    root = np.arange(n)
    while True:
        ra, rb = root[a], root[b]
        if (ra == rb).all():
            return root
        np.minimum.at(root, np.maximum(ra, rb), np.minimum(ra, rb))
        while (root[root] != root).any():
            root = root[root]


def label_components(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ids, labels) of the components of one sample: smallest id, by vectorised hooking and jumping."""
    ids, flat = np.unique(np.concatenate((src, dst)), return_inverse=True)
    return ids, ids[hooked(flat[: len(src)], flat[len(src) :], len(ids))]


#: Edges that a task reduces at once to those of a forest.
FOREST_EDGES = 1 << 20


def spanning(edges: DataFrame) -> DataFrame:
    """(src, dst): edges between vertices that `edges` connect, with the same components and fewer rows.

    Every task keeps one edge for each vertex it meets, to the smallest of those it has seen connected; what it holds
    is bounded by FOREST_EDGES, beyond which it gives edges out and begins anew.
    """

    def reduced(batches):
        none = np.zeros(0, np.int64)
        src, dst, held = [], [], 0

        def forest(most: int):
            """The (vertex, label) edges that are given out, and those that are held on."""
            ids, labels = label_components(np.concatenate((none, *src)), np.concatenate((none, *dst)))
            ids, labels = ids[ids != labels], labels[ids != labels]
            out = pa.record_batch({"src": ids, "dst": labels}) if len(ids) > most else None
            return out, ([none], [none], 0) if out is not None else ([ids], [labels], len(ids))

        for batch in batches:
            src.append(batch.column(0).to_numpy(zero_copy_only=False))
            dst.append(batch.column(1).to_numpy(zero_copy_only=False))
            held += batch.num_rows
            if held >= FOREST_EDGES:
                out, (src, dst, held) = forest(FOREST_EDGES // 2)
                if out is not None:
                    yield out
        out, _ = forest(0)
        if out is not None:
            yield out

    return edges.select("src", "dst").mapInArrow(reduced, "src long, dst long")


def components_local(sampled: DataFrame) -> DataFrame:
    """One task solves one simulation; a sample must fit a task (the planner sees to that)."""

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, labels = label_components(pdf["src"].to_numpy(), pdf["dst"].to_numpy())
        return pd.DataFrame({"sim": np.full(len(ids), pdf["sim"].iloc[0], np.int32), "id": ids, "label": labels})

    return sampled.groupBy("sim").applyInPandas(solve, "sim int, id long, label long")


#: Simulations of one wave: each wave is written and can be recomputed from the seed and its number alone.
WAVE = 1024


def components(
    g: CascadeGraph, runs: int, strategy: str = "auto", seed: int = 7, sampler: str = "xor", width: int = 8, wave: int = WAVE
) -> DataFrame:
    """The memo, by the named strategy; 'auto' asks the planner. More than `wave` simulations are solved wave by wave."""
    if strategy == "auto":
        from spreadmax.plans.planner import choose, wave_of

        plan = choose(g, runs, width, seed, sampler)
        strategy, wave = plan.strategy, min(wave, wave_of(plan, runs))
        if sampler == "independent" and strategy == "lanes":
            strategy = "star"  # lanes share one hash of an edge
    if strategy == "lanes":
        return components_lanes(g, runs, width, seed, sampler=sampler)
    solve = {"local": components_local, "minlabel": components_minlabel, "star": components_star}[strategy]
    if runs <= wave:
        return solve(fused_sample(g, runs, seed, sampler))
    memo = None
    for first in range(0, runs, wave):
        part = written(solve(fused_sample(g, min(runs, first + wave), seed, sampler, first=first)), "wave")
        memo = part if memo is None else memo.unionByName(part)
    return memo
