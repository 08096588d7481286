"""The experiments by name: each gives a table. `python -m spreadmax.plans.experiments NAME SF_DIR` prints one."""

from __future__ import annotations

import subprocess
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadmax.operators import components, diffusion, gains, measures, sampling, selection
from spreadmax.operators.graph import CascadeGraph, graph_stats
from spreadmax.operators.weights import weighted_cascade
from spreadmax.plans.workloads import breakdown, built, experiment
from spreadmax.session import local_session
from spreadmax.sources import graphs

SMALL = ["geo_forest", "cust_part"]
LARGE = ["copurchase", "cust_part", "part_supp", "cust_supp", "user_key", "geo_forest"]
SETTINGS = ["c001", "c01", "normal", "uniform"]
#: Seconds after which a run is stopped and reported without figures.
LIMIT = 60.0
Experiment = Callable[[SparkSession, str], DataFrame]


def datasets(s: SparkSession, d: str) -> DataFrame:
    """Vertices, edges, mean multiplicity and degrees of every graph."""
    out = None
    for n in sorted(graphs.BUILDERS):
        one = graph_stats(graphs.BUILDERS[n](s, d), n)
        out = one if out is None else out.unionByName(one)
    return out


def uniformity(s: SparkSession, d: str) -> DataFrame:
    """Binned distribution of draws by graph and sampler."""
    out = None
    for n in sorted(graphs.BUILDERS):
        g = CascadeGraph.of(graphs.BUILDERS[n](s, d), 0.01)
        for sampler in ("xor", "remix"):
            one = measures.draw_cdf(g, 32, sampler=sampler).withColumn("graph", F.lit(n)).withColumn("sampler", F.lit(sampler))
            out = one if out is None else out.unionByName(one)
    return out


def against_baseline(s: SparkSession, d: str) -> DataFrame:
    """Time, memory and score of the sequential baseline, the fused variant and the full method (k and k = 1), p = 0.01."""
    return experiment(s, d, LARGE, ["c001"], ["hybrid_lazy", "fused", "fused_memo", "fused_memo_k1"], k=50, runs=64, score_runs=1000, limit=LIMIT)


def against_comparator(s: SparkSession, d: str) -> DataFrame:
    """Time, memory and score of the full method and both comparator settings over the four weight settings."""
    return experiment(s, d, LARGE, SETTINGS, ["rr_0.5", "rr_0.13", "fused_memo"], k=50, runs=64, score_runs=1000, limit=LIMIT)


def comparator_speedup(s: SparkSession, d: str) -> DataFrame:
    return measures.speedup(against_comparator(s, d), "rr_0.13")


def speedup_breakdown(s: SparkSession, d: str) -> DataFrame:
    return breakdown(against_baseline(s, d))


def k_sweep(s: SparkSession, d: str) -> DataFrame:
    """Seconds for k seeds from one memo: components once, then selection only; share is that of the component stage."""
    start = time.perf_counter()
    m = gains.Memo.build(built(s, d, "cust_part", "c001"), 64)
    stage = time.perf_counter() - start
    rows = []
    for k in (1, 5, 10, 25, 50, 100, 500):
        start = time.perf_counter()
        out = selection.select_refresh(m, k)
        took = time.perf_counter() - start
        rows.append((k, stage, took, stage / (stage + took), out.visits, sum(x for _, x in out.seeds) / 64))
    return s.createDataFrame(rows, "k int, component_seconds double, selection_seconds double, component_share double, visits long, sigma double")


def queue_visits(s: SparkSession, d: str) -> DataFrame:
    rows = []
    for n in LARGE:
        for w in ("c001", "c01"):
            m = gains.Memo.build(built(s, d, n, w), 64)
            for kind, f in (("lazy", selection.select_lazy), ("refresh", selection.select_refresh)):
                out = f(m, 50)
                rows.append((n, w, kind, out.visits, out.scans))
    return s.createDataFrame(rows, "graph string, setting string, queue string, visits long, scans long")


def memory_by_weight(s: SparkSession, d: str) -> DataFrame:
    """Bytes of the dense memo, which do not depend on the weights, and of the sparse one, which do."""
    rows = []
    for n in SMALL:
        for w in SETTINGS:
            g = built(s, d, n, w)
            found = measures.memo_bytes(g.vertices.count(), 64, components.components(g, 64).count())
            rows.append((n, w, found["dense"], found["sparse"]))
    return s.createDataFrame(rows, "graph string, setting string, dense_bytes long, sparse_bytes long")


def live_against_all(s: SparkSession, d: str) -> DataFrame:
    """Rounds, live vertices and arcs visited when live vertices, all vertices or beside-live vertices take part."""
    rows = []
    for n in SMALL:
        for push in components.PUSHES:
            t = components.Trace()
            components.components_lanes(built(s, d, n, "c001"), 16, 16, push=push, trace=t)
            rows += [(n, push, r["round"], r["live"], r["arcs_visited"]) for r in t.rounds]
    return s.createDataFrame(rows, "graph string, push string, round int, live long, arcs_visited long")


def batch_widths(s: SparkSession, d: str, graph: str = "cust_part", runs: int = 32, widths: tuple[int, ...] = (8, 16, 32)) -> DataFrame:
    """Seconds and rounds of the lanes by the number of simulations that one row carries; the first run warms up and does not count."""
    g = built(s, d, graph, "c001")
    rows = []
    for i, width in enumerate((widths[0], *widths)):
        t = components.Trace()
        start = time.perf_counter()
        found = components.components_lanes(g, runs, width, trace=t).count()
        rows += [(graph, width, len(t.rounds), time.perf_counter() - start, found)] if i else []
    return s.createDataFrame(rows, "graph string, width int, rounds int, seconds double, memo_rows long")


def toy(s: SparkSession, d: str) -> DataFrame:
    return components.components_minlabel(graphs.toy_samples(s)).orderBy("sim", "id")


def cascade_models(s: SparkSession, d: str) -> DataFrame:
    """The same seeds under the independent, weighted and threshold models; weights of the weighted one are 1 / degree."""
    g = built(s, d, "geo_forest", "c01")
    seeds = s.createDataFrame([(1,), (5,)], "id long")
    out = None
    for model in ("ic", "wc", "lt", "lt_live"):
        one = diffusion.spread_mc(g, seeds, 100, model).agg(F.avg("reached").alias("sigma")).withColumn("model", F.lit(model))
        out = one if out is None else out.unionByName(one)
    return out.withColumn("mean_in_weight", F.lit(weighted_cascade(g.edges).agg(F.avg("w")).head()[0]))


def made_undirected(s: SparkSession, d: str) -> DataFrame:
    """Directed sources become undirected: page links and replies."""
    return graph_stats(graphs.page_link(s, d), "page_link").unionByName(graph_stats(graphs.graph_asof(s, d), "replies"))


def samplers(s: SparkSession, d: str) -> DataFrame:
    """Self-estimate against independent score by sampler and number of simulations."""
    rows = []
    g = built(s, d, "cust_part", "c001")
    for sampler in ("xor", "remix", "independent"):
        for runs in (8, 32, 128):
            m = gains.Memo.build(g, runs, sampler=sampler)
            out = selection.select_refresh(m, 5)
            sigma = sum(x for _, x in out.seeds) / runs
            score = diffusion.score_seeds(g, s.createDataFrame([(v,) for v, _ in out.seeds], "id long"), 200).head()
            differ = measures.distinct_samples(sampling.fused_sample(g, runs, sampler=sampler), runs).head()[0]
            rows.append((sampler, runs, sigma, float(score["sigma"]), measures.estimate_bias(sigma, float(score["sigma"])), differ))
    return s.createDataFrame(rows, "sampler string, runs int, self_sigma double, score double, bias double, distinct_samples long")


def scaling(s: SparkSession, d: str, cores: tuple[int, ...] = (1, 2, 4, 8)) -> DataFrame:
    """Seconds of the component stage by graph, weights and number of cores, each in a process of its own."""
    code = (
        "import sys, time\nfrom spreadmax.session import local_session\nfrom spreadmax.operators import gains\nfrom spreadmax.plans.workloads import built\n"
        "s = local_session(int(sys.argv[1]), 8)\ng = built(s, *sys.argv[2:5])\ngains.Memo.build(g, 8)\nt = time.perf_counter()\n"
        "gains.Memo.build(g, 256)\nprint('SECONDS', time.perf_counter() - t)"
    )
    rows = []
    for graph in ("copurchase", "cust_part"):
        for setting in ("c001", "c01"):
            first = None
            for c in cores:
                out = subprocess.run([sys.executable, "-c", code, str(c), d, graph, setting], capture_output=True, text=True, check=True).stdout
                took = float(out.rsplit("SECONDS", 1)[1])
                first = first or took
                rows.append((graph, setting, c, took, first / took))
    return s.createDataFrame(rows, "graph string, setting string, cores int, seconds double, speedup double")


def ratio(s: SparkSession, d: str) -> DataFrame:
    """Exact spread of the greedy seeds over that of the best seeds, on the complete toy graph and a path with a star."""
    edges = {
        "complete": graphs.cycle_of_friends(s),
        "star_path": s.createDataFrame([(1, 2, 1), (1, 3, 1), (1, 4, 1), (4, 5, 1), (5, 6, 1), (6, 7, 1), (7, 8, 1)], "src long, dst long, mult long"),
    }
    rows = []
    for name, e in edges.items():
        g = CascadeGraph.of(e, 0.3)
        m = gains.Memo.build(g, 512, sampler="remix")
        for k in (1, 2):
            own = [v for v, _ in selection.select_lazy(m, k).seeds]
            found = diffusion.spread_exact(g.edges, s.createDataFrame([("greedy", v) for v in own], "set string, id long")).head()["sigma"]
            best = diffusion.optimal_seeds(g.edges, k).head()["sigma"]
            rows.append((name, k, found, best, *measures.approx_ratio(found, best, k)))
    return s.createDataFrame(rows, "graph string, k int, greedy double, best double, ratio double, bound double, holds boolean")


EXPERIMENTS: dict[str, Experiment] = {
    f.__name__: f
    for f in (
        datasets, uniformity, against_baseline, against_comparator, comparator_speedup, speedup_breakdown, k_sweep, queue_visits, memory_by_weight, live_against_all, batch_widths, toy,
        cascade_models, made_undirected, samplers, scaling, ratio,
    )
}

if __name__ == "__main__":
    session = local_session(8, 16)
    session.sparkContext.setLogLevel("ERROR")
    EXPERIMENTS[sys.argv[1]](session, sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.01").show(100, False)
