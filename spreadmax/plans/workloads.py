"""The experiments over graphs, weight settings and methods: one row per run."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark import InheritableThread
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadmax.operators import baselines, gains, rrset, selection
from spreadmax.operators.diffusion import score_seeds
from spreadmax.operators.graph import CascadeGraph
from spreadmax.operators.measures import memo_bytes, memory_now, timed
from spreadmax.operators.weights import settings
from spreadmax.session import release, written
from spreadmax.sources.graphs import BUILDERS

RUNS = (
    "graph string, setting string, method string, k int, r int, seconds double, memo_bytes long, shuffle_bytes long, sigma_self double, "
    "score double, score_se double, visits long, seeds array<long>"
)
METHODS = ("fused_memo", "fused_memo_k1", "fused", "hybrid_lazy", "component", "rr_0.5", "rr_0.13", "degree")


def built(spark: SparkSession, sf_dir: str, graph: str, setting: str) -> CascadeGraph:
    edges = written(BUILDERS[graph](spark, sf_dir), "edges")
    g = CascadeGraph.of(edges, settings()[setting])
    return CascadeGraph(written(g.vertices, "vertices"), written(g.edges, "edges"))


def limited(spark: SparkSession, seconds: float | None, run: Callable[[], object]) -> object | None:
    """What `run` gives, or None where it takes longer: its jobs are cancelled then, one after the other, until it ends."""
    if seconds is None:
        return run()
    tag, box = f"limited-{uuid.uuid4().hex}", {}
    context = spark.sparkContext

    def go() -> None:
        context.addJobTag(tag)
        try:
            box["out"] = run()
        except Exception as error:
            box["error"] = error
        finally:
            context.removeJobTag(tag)

    thread = InheritableThread(target=go)
    thread.start()
    thread.join(seconds)
    if thread.is_alive():
        while thread.is_alive():
            context.cancelJobsWithTag(tag)
            thread.join(0.2)
        return None
    if "error" in box:
        raise box["error"]
    return box["out"]


def run_method(g: CascadeGraph, method: str, k: int, runs: int, most_sets: int | None = None) -> dict:
    """Seeds, seconds, memory figures and visits of one method.

    memo_bytes: what the method keeps between its stages: rows of the memo, members of the sets, or the bounds of
    the queue and the stored sample of one round; shuffle_bytes: what this run alone shuffled.
    """
    spark = g.edges.sparkSession
    extra = {"memo_bytes": 0, "visits": 0}

    def go() -> list[tuple[int, float]]:
        if method.startswith("fused_memo"):
            memo = gains.Memo.build(g, runs, "auto")
            extra["memo_bytes"] = memo_bytes(0, runs, memo.rows.count())["sparse"]
            out = selection.select_refresh(memo, 1 if method.endswith("k1") else k)
            extra["visits"] = out.visits
            release(memo.rows)
            return [(v, x / runs) for v, x in out.seeds]
        if method.startswith("rr_"):
            got = rrset.rrset_greedy(g, k, float(method[3:]), most=most_sets)
            extra["memo_bytes"] = 16 * got["members"]
            return [(v, 0.0) for v, _ in got["seeds"]]
        if method == "degree":
            return [(r["id"], 0.0) for r in baselines.degree_seeds(g.edges, k).orderBy("rank").collect()]
        chosen = {"fused": baselines.fused_greedy, "hybrid_lazy": baselines.hybrid_lazy_greedy, "component": baselines.component_greedy}
        out = chosen[method](g, k, runs)
        extra["visits"] = out.visits
        unit = runs if method == "fused" else 1
        return [(v, x / unit) for v, x in out.seeds]

    before = memory_now(spark)
    seeds, seconds = timed(go)
    extra["shuffle_bytes"] = memory_now(spark)["shuffle_write"] - before["shuffle_write"]
    if method in ("hybrid_lazy", "component", "fused"):
        # bounds of 16 bytes a vertex; a stored sample has 20 bytes an edge and simulation, the fused variant stores none
        extra["memo_bytes"] = 16 * g.vertices.count() + (0 if method == "fused" else 20 * baselines.sample_edges(g, runs).count())
    return {"seeds": [v for v, _ in seeds], "sigma": float(sum(x for _, x in seeds)), "seconds": seconds, **extra}


def experiment(
    spark: SparkSession, sf_dir: str, graphs: list[str], weight_settings: list[str], methods: list[str], k: int = 10, runs: int = 64,
    score_runs: int = 200, most_sets: int | None = None, limit: float | None = None,
) -> DataFrame:
    """The runs table: time, memory and independent score of methods on graphs and settings.

    A run beyond `limit` seconds is stopped: its row has no seconds, memory, score or seeds (a "-" in the published tables).
    """
    rows = []
    for graph in graphs:
        for setting in weight_settings:
            g = built(spark, sf_dir, graph, setting)
            for method in methods:
                number = 1 if method.endswith("k1") else k
                got = limited(spark, limit, lambda g=g, method=method: run_method(g, method, k, runs, most_sets))
                if got is None:
                    rows.append((graph, setting, method, number, runs, *[None] * 8))
                    continue
                own = spark.createDataFrame([(v,) for v in got["seeds"]], "id long")
                score = score_seeds(g, own, score_runs).head()
                rows.append(
                    (graph, setting, method, number, runs, got["seconds"], got["memo_bytes"], got["shuffle_bytes"], got["sigma"],
                     float(score["sigma"] or 0.0), float(score["se"] or 0.0), got["visits"], got["seeds"])
                )
    return spark.createDataFrame(rows, RUNS)


def breakdown(runs: DataFrame) -> DataFrame:
    """Seconds of each method and its share of the sequential baseline's."""
    base = runs.filter("method = 'hybrid_lazy'").select("graph", "setting", F.col("seconds").alias("base"))
    return runs.join(base, ["graph", "setting"]).select("graph", "setting", "method", "seconds", (F.col("base") / F.col("seconds")).alias("speedup"))
