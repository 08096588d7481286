"""The reverse-reachable-set comparator: sampled sets of vertices that reach a random root, covered greedily.

Sample sizes follow published martingale bounds. In an undirected graph the
vertices that reach the root are those that the root reaches.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadmax.functions.hashing import hash31
from spreadmax.operators.components import components_local, components_star, spanning
from spreadmax.operators.diffusion import reach_loop
from spreadmax.operators.graph import CascadeGraph, symmetrise
from spreadmax.operators.rrlocal import PACKED, packed, solver
from spreadmax.operators.selection import SetCoverage, select
from spreadmax.session import release, written

RR_SEED = 31
BUCKETS = 64
#: Edges of a piece that one task holds, about 100 bytes each; sets in larger components are found by rounds of joins.
PIECE_EDGES = 4_000_000
#: Components of fewer edges share a piece of about so many.
SMALL_EDGES = 65_536
#: Draws of a part of the sets of a piece at most, if every set passed over all edges, and (set, vertex) cells.
PART_DRAWS, PART_CELLS = 2_000_000_000, 16_000_000
#: Parts of the sets for each core at least, so that cores end at about the same time.
PARTS = 4
#: Draws of a part at least, so that a part is worth its copy of the piece.
LEAST_DRAWS = 100_000_000


@dataclass
class Bounds:
    """Numbers of sets: `search / guess` to test a guess of the optimum, `final / lower bound` for the last phase."""

    search: float
    final: float
    slack: float


def bounds(n: int, k: int, eps: float, ell: float = 1.0) -> Bounds:
    n = max(n, 2)
    k = min(k, n - 1)
    ell = ell * (1 + math.log(2) / math.log(n))
    choices = math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
    slack = math.sqrt(2) * eps
    share = 1 - 1 / math.e
    search = (2 + 2 / 3 * slack) * (choices + ell * math.log(n) + math.log(max(math.log2(n), 1.0000001))) * n / slack**2
    alpha = math.sqrt(ell * math.log(n) + math.log(2))
    beta = math.sqrt(share * (choices + ell * math.log(n) + math.log(2)))
    return Bounds(search, 2 * n * (share * alpha + beta) ** 2 / eps**2, slack)


def numbered(vertices: DataFrame) -> DataFrame:
    """(id, number): 0 .. n-1 by (id mod BUCKETS, id); buckets are numbered apart, so no task sees all vertices."""
    dealt = vertices.select("id", F.pmod("id", F.lit(BUCKETS)).alias("b"))
    counts = {r["b"]: r["count"] for r in dealt.groupBy("b").count().collect()}  # at most BUCKETS rows
    at, begins = 0, []
    for b in range(BUCKETS):
        begins.append(at)
        at += counts.get(b, 0)
    own = Window.partitionBy("b").orderBy("id")
    begin = F.get(F.array(*[F.lit(x).cast("long") for x in begins]), F.col("b").cast("int"))
    return dealt.select("id", (begin + F.row_number().over(own) - 1).alias("number"))


@dataclass
class Pieces:
    """A graph in pieces, for sets that stay within a component: a large component is a piece (bucket -1, label), small
    ones share one (bucket, label 0)."""

    packs: DataFrame  # bucket, label, chunk, arrays: the pieces that a task can hold, see `rrlocal.packed`
    far: DataFrame | None  # bucket, label, src, dst, h, thr: edges of the larger ones
    homes: DataFrame  # number, id, bucket, label: vertices by their number
    sizes: DataFrame  # bucket, label, m, n: edges and vertices of the pieces
    n: int

    @classmethod
    def of(cls, g: CascadeGraph) -> Pieces:
        edges = written(g.edges.select("src", "dst", "h", "thr"), "edges")
        forest = written(spanning(edges), "forest")
        solve = components_local if forest.count() <= PIECE_EDGES else components_star
        labels = written(solve(forest.select(F.lit(0).alias("sim"), "src", "dst")).select("id", "label"), "labels")
        by_label = edges.join(labels.withColumnRenamed("id", "src"), "src")
        own = written(by_label.groupBy("label").agg(F.count(F.lit(1)).alias("m")), "own")
        count = own.agg(F.coalesce(F.sum("m"), F.lit(0))).head()[0]
        buckets = max(1, -(-count // SMALL_EDGES))
        large = F.coalesce(F.col("m"), F.lit(0)) > SMALL_EDGES
        bucket = F.when(large, -1).otherwise(F.pmod(F.xxhash64("label"), F.lit(buckets))).cast("int").alias("bucket")
        label = F.when(large, F.col("label")).otherwise(0).alias("label")
        order = numbered(g.vertices).join(labels, "id", "left").withColumn("label", F.coalesce("label", "id")).join(own, "label", "left")
        first = F.when(F.col("id") == F.col("label"), F.coalesce("m", F.lit(0))).otherwise(0).alias("first")  # the edges of a component, once
        homes = written(order.select("number", "id", bucket, label, first), "homes")
        sizes = written(homes.groupBy("bucket", "label").agg(F.sum("first").alias("m"), F.count(F.lit(1)).alias("n")), "sizes")
        dealt = by_label.join(own, "label").select(bucket, label, "src", "dst", "h", "thr")
        beyond, far = sizes.filter(F.col("m") > PIECE_EDGES).select("bucket", "label"), None
        if beyond.limit(1).count():
            far = written(dealt.join(beyond, ["bucket", "label"], "left_semi"), "far")
            dealt = dealt.join(beyond, ["bucket", "label"], "left_anti")
        near = dealt.select("bucket", "label", "src", "dst", F.hash(F.col("h").cast("long")).alias("state"), "thr")
        tasks = max(4 * edges.sparkSession.sparkContext.defaultParallelism, 4 * count // PIECE_EDGES)
        packs = written(near.repartition(tasks, "bucket", "label").groupBy("bucket", "label").applyInArrow(packed, PACKED), "packs")
        for table in (edges, forest, labels, own):
            release(table)
        return cls(packs, far, homes, sizes, homes.count())

    def release(self) -> None:
        for table in (self.packs, self.far, self.homes, self.sizes):
            release(table)


def rr_sets(g: CascadeGraph, count: int, first: int = 0, seed: int = RR_SEED, pieces: Pieces | None = None) -> DataFrame:
    """(rr_id, id): the members of `count` sets. Set r has root hash(r, seed) mod n and draws of its own.

    A set stays within a component of the graph. The sets of a component that a task can hold are dealt to parts, each
    solved in one task beside a copy of the edges; those in larger ones are found by rounds of joins. `pieces`: the
    graph in pieces, where several calls share it.
    """
    spark = g.edges.sparkSession
    pieces = pieces or Pieces.of(g)
    if not pieces.n:
        return spark.createDataFrame([], "rr_id long, id long")
    keys = ["bucket", "label"]
    numbers = spark.range(first, first + count).select(F.col("id").alias("rr_id"), (hash31("id", seed) % pieces.n).cast("long").alias("number"))
    roots = numbers.join(pieces.homes, "number").select("rr_id", "id", *keys)
    asked = written(roots.groupBy(*keys).agg(F.count(F.lit(1)).alias("sets")).join(pieces.sizes, keys), "asked")
    held = F.col("m") <= PIECE_EDGES
    draws, cells = (F.col("sets").cast("double") * F.col(c) for c in ("m", "n"))
    near, total, spread = asked.filter(held).agg(F.count(F.lit(1)), F.coalesce(F.sum(draws), F.lit(0.0)), F.coalesce(F.sum(cells), F.lit(0.0))).head()
    unit = min(PART_DRAWS, max(LEAST_DRAWS, total / (PARTS * spark.sparkContext.defaultParallelism)))
    parts = F.ceil(F.greatest(draws / unit, cells / PART_CELLS, F.lit(1.0))).cast("int")
    tasks = max(1, 2 * (near + math.ceil(total / unit + spread / PART_CELLS)))  # at least twice the parts
    near = asked.filter(held).select(*keys, parts.alias("parts"))
    part = [*keys, "part"]
    dealt = roots.join(near, keys).withColumn("part", F.pmod("rr_id", "parts").cast("int")).select(*part, "rr_id", "id")
    copies = pieces.packs.join(near, keys).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    own, other = (x.repartition(tasks, *part).groupBy(*part) for x in (dealt, copies))
    sets = own.cogroup(other).applyInArrow(solver(seed), "rr_id long, id long")
    if pieces.far is not None:
        far = written(roots.join(asked.filter(~held).select(*keys), keys, "left_semi").select("rr_id", "id", *keys), "far")
        arcs = symmetrise(pieces.far.join(far.select(*keys).distinct(), keys, "left_semi").select("src", "dst", "h", "thr"))
        keep = hash31("h", "rr_id", seed) <= F.col("thr")
        sets = sets.unionByName(reach_loop(arcs, far.select("rr_id", "id"), ["rr_id"], keep).select("rr_id", "id"))
    return sets


def greedy_cover(rr: DataFrame, k: int) -> tuple[list[tuple[int, int]], int]:
    """[(id, newly covered sets)] and the covered number: one count of all members, then the lazy queue over blocks."""
    seeds = select(SetCoverage(rr), k, refresh=True).seeds
    return seeds, sum(n for _, n in seeds)


def rrset_greedy(g: CascadeGraph, k: int, eps: float, ell: float = 1.0, seed: int = RR_SEED, most: int | None = None) -> dict:
    """Seeds, their estimated spread, the number of sets of the last phase and the most members of any phase.

    Guesses of the optimum are halved until one is confirmed; the last phase draws
    fresh sets. `most` bounds the sets of a run for tests. A graph without vertices has no seeds.
    """
    pieces = Pieces.of(g)
    n = pieces.n
    if not n:
        return {"seeds": [], "sigma": 0.0, "sets": 0, "lower": 0.0, "members": 0}
    b = bounds(n, k, eps, ell)
    members = 0

    def phase(theta: int, first: int) -> tuple[list[tuple[int, int]], int]:
        nonlocal members
        rr = written(rr_sets(g, theta, first, seed, pieces), "rr")
        members = max(members, rr.count())
        found = greedy_cover(rr, k)
        release(rr)
        return found

    lower, first = 1.0, 0
    for i in range(1, max(2, math.ceil(math.log2(max(n, 2))))):
        guess = n / 2**i
        theta = math.ceil(b.search / guess)
        theta = min(theta, most) if most else theta
        _, covered = phase(theta, first)
        first += theta
        if n * covered / theta >= (1 + b.slack) * guess:
            lower = n * covered / theta / (1 + b.slack)
            break
    theta = max(1, math.ceil(b.final / lower))
    theta = min(theta, most) if most else theta
    seeds, covered = phase(theta, first)
    pieces.release()
    return {"seeds": seeds, "sigma": n * covered / theta, "sets": theta, "lower": lower, "members": members}
