"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

The graphs are small: most of their seconds are the latency of jobs, not work;
`copurchase` (the size of the smaller published networks) and p = 0.1 show the
work. The comparator draws all the sets of its bounds; beyond RR_LIMIT seconds
it is stopped and has no figure ("-" in `figures`), its seconds are the limit.
"""

from __future__ import annotations

import json
import os
import time

from spreadmax.operators import gains, measures, selection
from spreadmax.operators.diffusion import score_seeds
from spreadmax.operators.graph import CascadeGraph
from spreadmax.operators.rrset import rrset_greedy
from spreadmax.operators.weights import settings
from spreadmax.plans.workloads import limited
from spreadmax.session import local_session, written
from spreadmax.sources.graphs import BUILDERS

K, RUNS, RR_LIMIT = 50, 256, 120.0
#: Graph, weights, simulations.
CASES = [("geo_forest", "c001", RUNS), ("cust_part", "c001", RUNS), ("part_supp", "c001", RUNS), ("copurchase", "c001", 64), ("cust_part", "c01", 64)]


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "8"))
    spark = local_session(cpus, 4 * cpus, os.environ.get("BENCH_MEMORY", "8g"))
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    extra: dict[str, float | str] = {}

    def clock(name, run):
        start = time.perf_counter()
        out = run()
        seconds[name] = round(time.perf_counter() - start, 3)
        return out

    def graph(name, setting):
        edges = written(BUILDERS[name](spark, sf_dir), "edges")
        g = CascadeGraph.of(edges, settings()[setting])
        return CascadeGraph(written(g.vertices, "vertices"), written(g.edges, "edges"))

    for graph_name, setting, runs in CASES:  # warm and cold alike count
        name = graph_name if setting == "c001" else f"{graph_name}_{setting}"
        g = clock(f"build_{name}", lambda: graph(graph_name, setting))
        memo = clock(f"memo_{name}", lambda g=g, runs=runs: gains.Memo.build(g, runs))
        clock(f"first_seed_{name}", lambda memo=memo: selection.select_lazy(memo, 1))
        out = clock(f"seeds_{name}", lambda memo=memo: selection.select_refresh(memo, K))
        extra[f"visits_{name}"] = out.visits
        own = spark.createDataFrame([(v,) for v, _ in out.seeds], "id long")
        score = float(clock(f"score_{name}", lambda g=g, own=own: score_seeds(g, own, 200).head())["sigma"])
        self_sigma = sum(x for _, x in out.seeds) / runs
        extra |= {f"score_{name}": score, f"self_{name}": self_sigma, f"bias_{name}": round(measures.estimate_bias(self_sigma, score), 4)}
    g = graph("cust_part", "c001")
    clock("draw_cdf_cust_part", lambda: measures.draw_cdf(g, 64).collect())
    g = graph("geo_forest", "c001")
    got = clock("rrset_05_geo_forest", lambda: limited(spark, RR_LIMIT, lambda: rrset_greedy(g, 5, 0.5)))
    extra["rrset_05_geo_forest"] = "-" if got is None else got["sets"]
    print(json.dumps({"metric": "influence_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf_dir, "figures": extra}))


if __name__ == "__main__":
    main()
