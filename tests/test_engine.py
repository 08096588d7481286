"""The engine on worked examples, published invariants and the awkward rows of a graph."""

import math
import random
import re
from datetime import datetime, timedelta
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from spreadmax.functions import hashing
from spreadmax.operators import baselines, components, diffusion, gains, measures, rrlocal, rrset, sampling, selection, weights
from spreadmax.operators.connectivity import contracted_components
from spreadmax.operators.graph import CascadeGraph, canonicalise, degrees, graph_stats, induced_subgraph, vertices_of
from spreadmax.plans import experiments, planner
from spreadmax.plans.queries import QUERIES
from spreadmax.session import bucketed, release, written
from spreadmax.sources import files, graphs


def random_graph(spark, n=40, m=70, seed=1, w=0.4):
    rng = random.Random(seed)
    pairs = {tuple(sorted(rng.sample(range(n), 2))) for _ in range(m)}
    edges = spark.createDataFrame([(a, b, 1) for a, b in sorted(pairs)], "src long, dst long, mult long")
    return CascadeGraph.of(edges, w, spark.range(n + 3))  # three isolated vertices


def memo_rows(df):
    return sorted((r["sim"], r["id"], r["label"]) for r in df.select("sim", "id", "label").collect())


def brute_memo(sampled):
    out = []
    by = {}
    for r in sampled.collect():
        by.setdefault(r["sim"], []).append((r["src"], r["dst"]))
    for sim, pairs in by.items():
        root = {}

        def find(x, root=root):
            while root.setdefault(x, x) != x:
                x = root[x]
            return x

        for a, b in pairs:
            a, b = sorted((find(a), find(b)))
            root[b] = a
        out += [(sim, x, find(x)) for x in root]
    return sorted(out)


def test_murmur_goldens(spark):
    got = spark.sql("SELECT hash(1L, 2L) a, hash(0L, 5L) b, hash(1234L, 999999L) c").head()
    assert [x % 2**32 for x in got] == [3113790463, 345689190, 1901358254]


def test_hash_is_direction_oblivious(spark):
    df = spark.createDataFrame([(1, 2), (2, 1), (7, 9), (9, 7)], "a long, b long")
    for fn in ("murmur3", "xxhash64", "md5"):
        h = [r[0] for r in df.select(hashing.edge_hash("a", "b", fn)).collect()]
        assert h[0] == h[1] and h[2] == h[3] and h[0] != h[2] and 0 <= min(h)


def test_toy_example(spark):
    memo = components.components_minlabel(graphs.toy_samples(spark))
    m = gains.Memo.of(spark.range(1, 6).select("id"), memo, 2)
    assert {r["id"]: r["gain_sum"] for r in m.gains().collect()} == {1: 9, 2: 6, 3: 9, 4: 9, 5: 9}
    for f in (selection.select_scan, selection.select_lazy, selection.select_refresh):
        assert f(m, 2).seeds == [(1, 9), (2, 1)]


def test_golden_seeds(spark):
    g = CascadeGraph.of(graphs.cust_part(spark, "/root/testdata/sf0.01"), 0.01)
    m = gains.Memo.build(g, 16)
    out = selection.select_lazy(m, 5)
    assert out.seeds == [(2285, 51), (1392, 48), (1130, 47), (2958, 46), (174, 45)] and out.visits == 6
    assert m.rows.select("id").distinct().count() == 3463


@pytest.mark.parametrize("sampler", ["xor", "remix"])
def test_strategies_agree(spark, sampler):
    g = random_graph(spark)
    want = brute_memo(sampling.fused_sample(g, 10, sampler=sampler))
    for strategy in ("local", "minlabel", "star"):
        assert memo_rows(components.components(g, 10, strategy, sampler=sampler)) == want
    assert memo_rows(components.components_lanes(g, 10, 8, sampler=sampler)) == want  # 10 is no multiple of 8


@pytest.mark.parametrize("push", ["all", "pull"])
def test_pushes_agree(spark, push):
    g = random_graph(spark, seed=2)
    trace = components.Trace()
    assert memo_rows(components.components_lanes(g, 4, 4, push=push, trace=trace)) == brute_memo(sampling.fused_sample(g, 4))
    assert trace.rounds[-1]["live"] == 0


def test_selections_agree_and_gains_fall(spark):
    g = random_graph(spark, 60, 90, 3, 0.3)
    m = gains.Memo.build(g, 12)
    scan = selection.select_scan(m, 6)
    for kind in ({"block": 3}, {"block": 7, "lookahead": True}, {"refresh": True, "block": 5}, {}):
        assert selection.select_lazy(m, 6, **kind).seeds == scan.seeds
    own = [x for _, x in scan.seeds]
    assert own == sorted(own, reverse=True)
    assert baselines.fused_greedy(g, 3, 12).seeds == scan.seeds[:3]


def test_all_vertices_when_k_is_large(spark):
    g = random_graph(spark, 8, 8, 4)
    m = gains.Memo.build(g, 5)
    out = selection.select_lazy(m, 99, block=4)
    assert len(out.seeds) == 11 and sum(x for _, x in out.seeds) == 11 * 5


def test_extreme_weights(spark):
    zero, one = random_graph(spark, w=0.0), random_graph(spark, w=1.0)
    assert sampling.fused_sample(zero, 6).count() == 0
    assert {r["gain_sum"] for r in gains.Memo.build(zero, 6).gains().collect()} == {6}
    assert sampling.fused_sample(one, 6).count() == 6 * one.edges.count()
    whole = contracted_components(one.edges)
    assert gains.Memo.build(one, 1).rows.select("id", "label").exceptAll(whole).count() == 0


def test_awkward_rows(spark):
    raw = spark.createDataFrame([(1, 2), (2, 1), (1, 1), (None, 3), (3, None), (2, 5), (2, 5)], "src long, dst long")
    assert sorted(map(tuple, canonicalise(raw).collect())) == [(1, 2, 2), (2, 5, 2)]
    empty = CascadeGraph.of(canonicalise(raw.limit(0)), 0.5)
    assert gains.Memo.build(empty, 3).gains().count() == 0 and selection.select_lazy(gains.Memo.build(empty, 3), 2).seeds == []


def test_hub_and_ties(spark):
    star = spark.createDataFrame([(0, i, 1) for i in range(1, 30)] + [(100, 101, 1)], "src long, dst long, mult long")
    m = gains.Memo.build(CascadeGraph.of(star, 1.0), 4)
    assert selection.select_lazy(m, 3, block=2).seeds == [(0, 120), (100, 8)] + [(1, 0)]


def test_contraction_of_long_paths(spark):
    path = spark.range(200).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    got = contracted_components(path)
    assert got.count() == 201 and got.agg(F.max("label")).head()[0] == 0
    loops = contracted_components(spark.createDataFrame([(4, 4), (7, 6)], "src long, dst long"))
    assert sorted(map(tuple, loops.collect())) == [(4, 4), (6, 6), (7, 6)]


def test_giant_components_join_by_broadcast(spark, monkeypatch):
    g = random_graph(spark, w=0.9)
    memo = components.components(g, 4)
    plain = sorted(map(tuple, gains.sized(memo, gains.component_sizes(memo)).select("sim", "id", "label", "size").collect()))
    monkeypatch.setattr(gains, "HEAVY_ROWS", 10)
    assert sorted(map(tuple, gains.sized(memo, gains.component_sizes(memo)).select("sim", "id", "label", "size").collect())) == plain


def test_memo_survives_saving(spark, tmp_path):
    m = gains.Memo.build(random_graph(spark), 6)
    m.save(str(tmp_path / "memo"))
    again = gains.Memo.load(spark, str(tmp_path / "memo"))
    assert again.runs == 6 and selection.select_lazy(again, 4).seeds == selection.select_lazy(m, 4).seeds


def test_planner(spark):
    g = random_graph(spark, w=0.1)
    assert planner.choose(g, 8).strategy == "local"
    assert planner.choose(g, 8, width=2, task_bytes=0).strategy == "star"
    assert planner.choose(random_graph(spark, w=1.0), 8, task_bytes=0).strategy == "lanes"


def _tiny(spark):
    rows = [(0, 1, 1), (1, 2, 1), (2, 3, 1), (0, 3, 1), (3, 4, 1), (5, 6, 1)]
    return CascadeGraph.of(spark.createDataFrame(rows, "src long, dst long, mult long"), 0.4)


def _exact(pairs, p, seeds):
    total = 0.0
    for mask in range(1 << len(pairs)):
        near, prob = {}, 1.0
        for k, (a, b) in enumerate(pairs):
            prob *= p if mask >> k & 1 else 1 - p
            if mask >> k & 1:
                near.setdefault(a, []).append(b)
                near.setdefault(b, []).append(a)
        seen, todo = set(seeds), list(seeds)
        while todo:
            for x in near.get(todo.pop(), []):
                if x not in seen:
                    seen.add(x)
                    todo.append(x)
        total += prob * len(seen)
    return total


def test_exact_spread_and_approximation(spark):
    g = _tiny(spark)
    pairs = [(r["src"], r["dst"]) for r in g.edges.collect()]
    sets = spark.createDataFrame([("0", 0), ("3", 3), ("03", 0), ("03", 3)], "set string, id long")
    got = {r["set"]: r["sigma"] for r in diffusion.spread_exact(g.edges, sets).collect()}
    for name, own in (("0", [0]), ("3", [3]), ("03", [0, 3])):
        assert got[name] == pytest.approx(_exact(pairs, 0.4, own), abs=1e-5)
    best = max(_exact(pairs, 0.4, c) for c in combinations(range(7), 2))
    row = diffusion.optimal_seeds(g.edges, 2).head()
    assert row["sigma"] == pytest.approx(best, abs=1e-5)
    seeds = [v for v, _ in selection.select_lazy(gains.Memo.build(g, 512, sampler="remix"), 2).seeds]
    assert _exact(pairs, 0.4, seeds) >= (1 - (1 - 1 / 2) ** 2) * best


def test_estimates_meet_the_exact_spread(spark):
    g = _tiny(spark)
    pairs = [(r["src"], r["dst"]) for r in g.edges.collect()]
    row = diffusion.score_seeds(g, spark.createDataFrame([(3,)], "id long"), 2000).head()
    assert abs(row["sigma"] - _exact(pairs, 0.4, [3])) < 4 * row["se"]
    top = baselines.hybrid_lazy_greedy(g, 2, 400).seeds
    lazy = baselines.lazy_forward(g, 2, 400).seeds
    assert {v for v, _ in top} <= set(range(7)) and lazy[0][1] >= lazy[1][1] - 0.3
    assert baselines.plain_greedy(g, 1, 64).seeds[0][1] == pytest.approx(baselines.lazy_forward(g, 1, 64).seeds[0][1])
    assert baselines.component_greedy(g, 2, 64).seeds[0][0] == baselines.hybrid_lazy_greedy(g, 1, 64).seeds[0][0]


def test_lookahead_keeps_the_seeds_of_the_simulated_queue(spark):
    edges = spark.createDataFrame([(1, v) for v in range(2, 8)] + [(7, 8), (8, 9), (10, 11)], "src long, dst long").withColumn("mult", F.lit(1).cast("long"))
    g = CascadeGraph.of(edges, 0.5)
    plain = baselines.lazy_forward(g, 3, 16, ahead=1)
    ahead = baselines.lazy_forward(g, 3, 16, ahead=1, lookahead=True)
    assert ahead.seeds == plain.seeds and len(plain.seeds) == 3
    assert ahead.visits <= plain.visits


def test_lookahead_saves_a_visit():
    covers = {1: set(range(1, 11)), 2: {1, 2, 3, *range(11, 17)}, 3: {1, 2, 3, 4, *range(17, 21)}, 4: {21}}
    gain = lambda seeds, v: len(covers[v] - set().union(*(covers[x] for x in seeds)))
    evaluate = lambda seeds, vs: {v: gain(seeds, v) for v in vs}
    beside = lambda seeds, vs, best: (evaluate(seeds, vs), evaluate([*seeds, best], vs))
    first = evaluate([], list(covers))
    want = [(1, 10), (2, 6), (3, 4)]
    assert selection.lazy_greedy(first, evaluate, 3, 1) == (want, 3)
    assert selection.lazy_greedy(first, evaluate, 3, 1, beside) == (want, 2)


def test_forest_closed_form(spark):
    edges = graphs.geo_forest(spark, "/root/testdata/sf0.01")
    exact = diffusion.forest_exact(edges, lambda c: F.pmod(c, F.lit(4)), 0.1)
    best = exact.orderBy(F.desc("sigma"), "id").head()
    assert (best["id"], round(best["sigma"], 3)) == (9, 8.778)
    assert exact.agg(F.sum("sigma")).head()[0] == pytest.approx(2818.6018, abs=1e-2)


def test_threshold_model_equals_live_edges_on_average(spark):
    g = random_graph(spark, 20, 35, 6)
    seeds = spark.createDataFrame([(0,), (1,)], "id long")
    a = diffusion.spread_mc(g, seeds, 600, "lt").agg(F.avg("reached"), F.stddev("reached")).head()
    b = diffusion.spread_mc(g, seeds, 600, "lt_live", seed=5).agg(F.avg("reached"), F.stddev("reached")).head()
    assert abs(a[0] - b[0]) < 5 * math.hypot(a[1], b[1]) / math.sqrt(600)


def test_weighted_cascade_round(spark):
    """A vertex of degree d with l active neighbours turns active with 1 - (1 - 1/d)**l."""
    edges = spark.createDataFrame([(0, 9, 1), (1, 9, 1), (2, 9, 1), (3, 9, 1)], "src long, dst long, mult long")
    seeds = spark.createDataFrame([(0,), (1,)], "id long")
    got = diffusion.cascade_weighted(edges, seeds, 4000).filter("id = 9").count() / 4000
    assert abs(got - (1 - (3 / 4) ** 2)) < 0.03


def test_comparator(spark):
    g = CascadeGraph.of(graphs.supp_supp(spark, "/root/testdata/sf0.001"), 0.05)
    got = rrset.rrset_greedy(g, 2, 0.5)
    own = spark.createDataFrame([(v,) for v, _ in got["seeds"]], "id long")
    score = diffusion.score_seeds(g, own, 800).head()
    assert abs(got["sigma"] - score["sigma"]) < 0.15 * score["sigma"] + 4 * score["se"]
    memo = [v for v, _ in selection.select_lazy(gains.Memo.build(g, 256), 2).seeds]
    ours = diffusion.score_seeds(g, spark.createDataFrame([(v,) for v in memo], "id long"), 800).head()
    assert score["sigma"] >= 0.9 * ours["sigma"] and ours["sigma"] >= 0.95 * score["sigma"]
    assert rrset.bounds(1000, 10, 0.13).final > rrset.bounds(1000, 10, 0.5).final


def test_draws_are_uniform(spark):
    g = CascadeGraph.of(graphs.user_key(spark, "/root/testdata/sf0.001"), 0.01)
    for sampler in ("xor", "remix"):
        assert measures.ks_uniform(measures.draw_cdf(g, 64, sampler=sampler)).head()[0] < 0.05
    n = 739 * 64
    assert measures.ks_uniform(measures.draw_cdf(g, 64, sampler="remix")).head()[0] < 1.63 / math.sqrt(n) * 2


def test_weights(spark):
    e = graphs.cust_part(spark, "/root/testdata/sf0.001")
    for w, low, high in ((weights.uniform(), 0.0, 0.1), (weights.gaussian(), 0.0, 1.0)):
        row = CascadeGraph.of(e, w).edges.agg(F.min("w"), F.max("w"), F.avg("w"), F.avg((F.col("w") <= 0.1).cast("int"))).head()
        assert low <= row[0] and row[1] <= high and abs(row[2] - 0.05) < 0.003 and row[3] > 0.94
    assert CascadeGraph.of(e, 0.0).edges.agg(F.max("thr")).head()[0] == -1
    assert CascadeGraph.of(e, 1.0).edges.agg(F.min("thr")).head()[0] == hashing.INT_MAX


def test_monotone_in_weight(spark):
    low, high = sampling.fused_sample(random_graph(spark, w=0.2), 8), sampling.fused_sample(random_graph(spark, w=0.5), 8)
    assert low.exceptAll(high).count() == 0 and high.count() > low.count()


def test_files(spark, tmp_path):
    (tmp_path / "e.tsv").write_text("# comment\n1\t2\t0.5\n3\t4\n")
    (tmp_path / "e.txt").write_text("# comment\n1   2\n\n3 4 0.25\n")
    assert sorted(map(str, files.read_edges(spark, str(tmp_path / "e.tsv")).collect())) == ["Row(src=1, dst=2, w=0.5)", "Row(src=3, dst=4, w=None)"]
    assert files.read_edges(spark, str(tmp_path / "e.txt"), "text").count() == 2
    df = files.from_rows(spark, [(1, 2, 0.5)], files.SCHEMA)
    for fmt in ("json", "parquet"):
        files.write(df, str(tmp_path / fmt), fmt)
        assert files.read_edges(spark, str(tmp_path / fmt), fmt).count() == 1


def test_plans(spark, small, capsys):
    """Filters and columns reach the scan; sampling needs no shuffle; no cartesian product in a superstep."""
    graphs.graph_between(spark, small, "1995-01-01", "1996-01-01").explain("formatted")
    text = capsys.readouterr().out
    assert re.search(r"PushedFilters: .*GreaterThanOrEqual\(o_orderdate", text) and "o_totalprice" not in text
    g = CascadeGraph.of(spark.range(9).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).alias("mult")), 0.5)
    sampling.fused_sample(g, 8).explain()
    assert "Exchange" not in capsys.readouterr().out
    batches = components.batch_table(spark, 8, 8, 7)
    lanes = components.lanes_init(g, batches, 8)
    components.lane_messages(lanes, g.arcs, batches, 8).explain()
    text = capsys.readouterr().out
    assert "Cartesian" not in text and "partial_min" in text


def test_graph_helpers(spark):
    g = random_graph(spark)
    row = graph_stats(g.edges, "x").head()
    assert row["mean_degree"] == pytest.approx(2 * row["m"] / row["n"], abs=1e-5)
    assert degrees(g.edges).agg(F.sum("deg")).head()[0] == 2 * row["m"]
    ids = spark.range(10)
    assert induced_subgraph(g.edges, ids).filter("src > 9 OR dst > 9").count() == 0
    assert vertices_of(g.edges).count() == row["n"]


def test_experiments_do_not_cap_the_comparator(spark, small, monkeypatch):
    from spreadmax.plans import workloads

    asked = []

    def greedy(g, k, eps, **options):
        asked.append((eps, options.get("most")))
        return {"seeds": [(0, 1)], "sets": 1, "members": 1}

    monkeypatch.setattr(workloads.rrset, "rrset_greedy", greedy)
    workloads.experiment(spark, small, ["geo_forest"], ["c01"], ["rr_0.5", "rr_0.13"], k=1, runs=1, score_runs=1)
    assert asked == [(0.5, None), (0.13, None)]


def test_runs_beyond_their_limit_are_stopped(spark):
    import time

    from spreadmax.plans.workloads import limited

    slow = lambda: [spark.range(3_000_000_000, numPartitions=400).selectExpr("sum(sqrt(id) * sin(id))").head() for _ in range(50)]
    start = time.perf_counter()
    assert limited(spark, 1.0, slow) is None and time.perf_counter() - start < 30
    assert limited(spark, 30.0, lambda: spark.range(5).count()) == 5 == limited(spark, None, lambda: spark.range(5).count())
    with pytest.raises(ZeroDivisionError):
        limited(spark, 30.0, lambda: 1 / 0)


def test_scores_by_components_and_by_rounds_agree(spark):
    g = random_graph(spark)
    for ids in ([0], [3, 41, 7], [41]):
        seeds = spark.createDataFrame([(i,) for i in ids], "id long")
        assert diffusion.score_seeds(g, seeds, 40).head() == diffusion.score_seeds(g, seeds, 40, by="rounds").head()


def test_driver_memory_of_the_queue_is_bounded(spark):
    m = gains.Memo.build(random_graph(spark), 16)
    want = selection.select_scan(m, 6).seeds
    assert selection.select_lazy(m, 6, block=3, held=1).seeds == want
    assert selection.select_lazy(m, 6, block=3, held=1, lookahead=True).seeds == want
    heavy = gains.sized(m.rows.select("sim", "id", "label"), gains.component_sizes(m.rows), heavy_rows=1, heavy_labels=3)
    assert sorted(map(tuple, heavy.select("sim", "id", "label", "size").collect())) == sorted(map(tuple, m.rows.select("sim", "id", "label", "size").collect()))


def test_comparator_without_vertices(spark):
    empty = CascadeGraph.of(spark.createDataFrame([], "src long, dst long, mult long"), 0.1)
    assert rrset.rrset_greedy(empty, 2, 0.5)["seeds"] == [] and rrset.rr_sets(empty, 5).count() == 0


def test_stream_memo_goes_on_where_it_stopped(spark, tmp_path):
    import pyarrow as pa
    import pyarrow.parquet as pq

    from spreadmax.streaming import edges as stream

    rng = random.Random(3)
    rows = [(i, None, rng.randrange(30), "view", 1.0, '{"k": %d}' % rng.randrange(30)) for i in range(240)]
    all_rows = spark.createDataFrame(rows, stream.EVENTS)
    place, source = f"file://{tmp_path}/place", tmp_path / "source"
    source.mkdir()
    kinds = [pa.int64(), pa.timestamp("us"), pa.int64(), pa.string(), pa.float64(), pa.string()]
    names = ["event_id", "ts", "user_id", "event_type", "value", "props"]
    for part in range(3):
        own = zip(*[r for r in rows if r[0] % 3 == part], strict=True)
        pq.write_table(pa.table([pa.array(x, t) for x, t in zip(own, kinds, strict=True)], names=names), source / f"events{part}.parquet")
        got = stream.stream_memo(spark, str(source), 0.3, 4, place=place)
    whole = canonicalise(all_rows.selectExpr("2 * user_id AS src", "2 * CAST(get_json_object(props, '$.k') AS BIGINT) + 1 AS dst"))
    assert memo_rows(got) == brute_memo(sampling.fused_sample(CascadeGraph.of(whole, 0.3), 4))
    assert len(stream._versions(spark, f"{place}/memo")) == 2


def test_latest_before(spark):
    rng = random.Random(3)
    rows = []
    for i in range(600):  # a hot key, ties, gaps of several spans, missing users, keys and times
        at = None if i % 97 == 0 else datetime(2024, 1, 1) + timedelta(seconds=40 * rng.randrange(900))
        rows.append((i, None if i % 7 == 0 else rng.randrange(50), None if i % 31 == 0 else rng.choice([1, 1, 2, 3]), at))
    events = spark.createDataFrame(rows, "event_id long, user_id long, k long, ts timestamp_ntz")
    got = {r["event_id"]: r["before"] for r in graphs.latest_before(events, span=300).collect()}
    last, want = {}, {}
    for i, user, k, _ in sorted(rows, key=lambda r: (r[3] is not None, r[3] or datetime.min, r[0])):
        want[i] = last.get(k)
        last[k] = last.get(k) if user is None else user
    assert got == want
    assert graphs.latest_before(events.limit(0)).count() == 0


def test_similar_vectors_by_blocks(spark, small):
    one, many = (graphs.embed_sim(spark, small, block_rows=n) for n in (1 << 20, 37))
    assert "NestedLoop" not in many._jdf.queryExecution().toString()
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, many.collect()))


def test_large_baskets_are_paired_by_blocks(spark):
    rows = [(1, i) for i in range(40)] + [(2, i) for i in range(30, 45)] + [(3, 7), (None, 1), (3, None), (3, 7)]
    df = spark.createDataFrame(rows, "k long, i long")
    want = {}
    for key in (1, 2):
        for pair in combinations([i for k, i in rows if k == key], 2):
            want[pair] = want.get(pair, 0) + 1
    for basket in (4, 512):
        got = graphs._co_occurring(df, "k", "i", basket).collect()
        assert {(r["src"], r["dst"]): r["mult"] for r in got} == want and len(got) == len(want)


def test_bucketed_tables_are_joined_without_their_shuffle(spark):
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        g = random_graph(spark)
        arcs = bucketed(g.arcs.select("u", "v", "h", "thr"), "u", "arcs")
        batches = components.batch_table(spark, 4, 4, 7)
        lanes = written(components.lanes_init(g, batches, 4), "lanes")
        plans = [components.lane_messages(lanes, side, batches, 4)._jdf.queryExecution().executedPlan().toString() for side in (arcs, written(arcs, "arcs"))]
        assert [p.count("Exchange hashpartitioning") for p in plans] == [2, 3]
        assert arcs.count() == 2 * g.edges.count()
        name = arcs._table
        release(arcs)
        assert not spark.catalog.tableExists(name)
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_independent_sampler(spark):
    g = random_graph(spark)
    want = brute_memo(sampling.fused_sample(g, 6, sampler="independent"))
    assert memo_rows(components.components(g, 6, sampler="independent")) == want
    assert want != brute_memo(sampling.sample_edges(g, 6))  # the score oracle's draws are others
    with pytest.raises(ValueError):
        components.components(g, 6, "lanes", sampler="independent")


def test_batch_widths(spark, small):
    rows = experiments.batch_widths(spark, small, "geo_forest", 8, (4, 8)).collect()
    assert [r["width"] for r in rows] == [4, 8] and rows[0]["memo_rows"] == rows[1]["memo_rows"] > 0 and rows[0]["rounds"] == rows[1]["rounds"]


def test_long_rounds_of_the_queue_end_on_the_cluster(spark, monkeypatch):
    g = random_graph(spark, 60, 120, 5, 0.5)
    m = gains.Memo.build(g, 6)
    plain = selection.select_lazy(m, 6, block=1024)  # all visits on the driver
    fetched = []
    fetch = selection._Bounds.fetch
    monkeypatch.setattr(selection._Bounds, "fetch", lambda self: fetched.append(1) or fetch(self))
    by_scans = selection.select_lazy(m, 6, block=2)
    assert by_scans.seeds == plain.seeds == selection.select_scan(m, 6).seeds
    assert by_scans.visits == plain.visits > 50
    assert len(fetched) < plain.visits / 2  # blocks were not fetched one by one


def brute_cokeep(sampled, least):
    by = {}
    for r in sampled.collect():
        by.setdefault((r["src"], r["dst"]), set()).add(r["sim"])
    return sum(len(by[a] & by[b]) >= least for a, b in combinations(by, 2))


def test_pairs_kept_together_are_counted_without_pairs(spark, monkeypatch):
    sampled = written(sampling.fused_sample(random_graph(spark, 30, 60, 7, 0.3), 12), "sampled")
    want = brute_cokeep(sampled, 2)
    got = measures.pair_cokeep(sampled, 12, 0.3)
    assert got.head()["pairs"] == want > 0
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert not re.search(r"Join Inner.*sim#\d+ = sim#\d+", plan)  # edges do not meet through their simulation
    assert measures.pair_cokeep(sampled, 12, 0.5).head()["pairs"] == brute_cokeep(sampled, 3)
    monkeypatch.setattr(measures, "SUBSET_RUNS", 3)  # larger groups are compared
    assert measures.pair_cokeep(sampled, 12, 0.3).head()["pairs"] == want


def test_spreads_of_all_vertices_share_traversals(spark, monkeypatch):
    g = random_graph(spark, 14, 20, 9, 0.4)
    monkeypatch.setattr(baselines, "reach_loop", lambda *_: pytest.fail("a traversal for each vertex"))
    sampled = {}
    for r in sampling.sample_edges(g, 5, 101).collect():
        sampled.setdefault(r["sim"], []).append((r["src"], r["dst"]))

    def reached(ids):
        n = 0
        for sim in range(5):
            seen = set(ids)
            while more := {y for a, b in sampled.get(sim, []) for x, y in ((a, b), (b, a)) if x in seen} - seen:
                seen |= more
            n += len(seen)
        return n / 5

    for seeds in ([], [3], [3, 15]):  # 15 is isolated
        got = {r["id"]: r["gain_sum"] for r in baselines.simulated_spreads(g, seeds, 5).collect()}
        assert got == {v: reached([*seeds, v]) for v in range(17) if v not in seeds}


def test_pairs_of_remixed_samples_kept_together(spark):
    sampled = written(sampling.fused_sample(random_graph(spark, 30, 60, 8, 0.3), 12, sampler="remix"), "sampled")
    got = measures.pair_cokeep(sampled, 12, 0.3)
    assert got.head()["pairs"] == brute_cokeep(sampled, 2) > 0
    assert not re.search(r"Join Inner.*sim#\d+ = sim#\d+", got._jdf.queryExecution().optimizedPlan().toString())


def test_lookahead_bounds_need_no_traversal_of_each_vertex(spark, monkeypatch):
    monkeypatch.setattr(baselines, "reach_loop", lambda *_: pytest.fail("a traversal for each vertex"))
    g = random_graph(spark, 14, 20, 9, 0.4)
    assert baselines.lazy_forward(g, 1, 5, lookahead=True).seeds == baselines.component_greedy(g, 1, 5).seeds


def test_plain_greedy_needs_no_traversal_of_each_vertex(spark, monkeypatch):
    monkeypatch.setattr(baselines, "reach_loop", lambda *_: pytest.fail("a traversal for each vertex"))
    g = random_graph(spark, 14, 20, 9, 0.4)
    out = baselines.plain_greedy(g, 2, 5)
    assert out.seeds[0] == baselines.component_greedy(g, 1, 5).seeds[0] and out.visits == 17 + 16


@pytest.mark.parametrize("share", [0.0, 1 / 16, 99.0])
def test_reverse_sets_of_a_piece_are_those_of_rounds(spark, share):
    """Passes over the edges (0), expanded vertices (99) and the mix of both draw what the column hash draws."""
    edges = [(r["src"], r["dst"], 1) for r in random_graph(spark, 60, 150, 4).edges.collect()]
    edges += [(1000 + i, 1001 + i, 1) for i in range(9)] + [(5_000_000_000, 5_000_000_001, 1), (70, 71, 1)]
    weight = F.when(F.col("src") == 70, 0.0).when(F.col("src") > 999, 1.0).otherwise(F.lit(0.1) + F.col("dst") % 3 * 0.1)
    g = CascadeGraph.of(spark.createDataFrame(edges, "src long, dst long, mult long"), weight, spark.range(63))
    sets, roots = 40, {}
    numbers = {r["number"]: r["id"] for r in rrset.numbered(g.vertices).collect()}
    first = (1 << 32) - 20  # the upper half of the number counts too
    for r in spark.range(first, first + sets).select("id", hashing.hash31("id", 31).alias("q")).collect():
        roots[r["id"]] = numbers[r["q"] % len(numbers)]
    starts = spark.createDataFrame(list(roots.items()), "rr_id long, id long")
    keep = hashing.hash31("h", "rr_id", 31) <= F.col("thr")
    rounds = diffusion.reach_loop(g.arcs.select("u", "v", "h", "thr"), starts, ["rr_id"], keep)
    want = sorted((r["rr_id"], r["id"]) for r in rounds.collect())
    flat = [(r["src"], r["dst"], r["state"], r["thr"]) for r in g.edges.select("src", "dst", F.hash(F.col("h").cast("long")).alias("state"), "thr").collect()]
    tables = pa.table({"rr_id": list(roots), "id": list(roots.values())}), pa.Table.from_pylist([dict(zip(("src", "dst", "state", "thr"), x, strict=True)) for x in flat], pa.schema({"src": pa.int64(), "dst": pa.int64(), "state": pa.int32(), "thr": pa.int32()}))
    before, rrlocal.PASS_SHARE = rrlocal.PASS_SHARE, share
    try:
        got = rrlocal.solver(31)(*tables)
    finally:
        rrlocal.PASS_SHARE = before
    assert sorted(zip(got["rr_id"].to_pylist(), got["id"].to_pylist(), strict=True)) == want
    assert sorted((r["rr_id"], r["id"]) for r in rrset.rr_sets(g, sets, first).collect()) == want


def test_reverse_sets_need_rounds_only_in_components_beyond_a_task(spark, monkeypatch):
    g = random_graph(spark, 50, 80, 6, 0.3)
    monkeypatch.setattr(rrset, "PIECE_EDGES", 3)  # also labels by contraction
    monkeypatch.setattr(rrset, "SMALL_EDGES", 2)
    want = sorted((r["rr_id"], r["id"]) for r in rrset.rr_sets(g, 60).collect())
    monkeypatch.setattr(rrset, "reach_loop", lambda *_: pytest.fail("rounds of joins"))
    monkeypatch.setattr(rrset, "PIECE_EDGES", 1000)
    monkeypatch.setattr(rrset, "LEAST_DRAWS", 100)  # several parts
    assert sorted((r["rr_id"], r["id"]) for r in rrset.rr_sets(g, 60).collect()) == want
    assert rrset.rrset_greedy(g, 2, 0.5)["sets"] > 60


def test_similar_vectors_are_multiplied_as_blocks(spark, tmp_path):
    rng = random.Random(3)
    vectors = [[rng.gauss(0, 1) for _ in range(6)] for _ in range(40)] + [[1.0, 2.0]] * 2 + [[0.0] * 6, None]
    vectors[7] = [2 * x for x in vectors[5]]
    df = spark.createDataFrame(list(enumerate(vectors)), "vec_id int, embedding array<float>")
    df.write.parquet(f"{tmp_path}/embeddings.parquet")
    vectors = {r["vec_id"]: r["embedding"] for r in df.collect() if r["embedding"] and any(r["embedding"])}
    dot = lambda x, y: sum(a * b for a, b in zip(x, y, strict=True))
    want = set()
    for a, b in combinations(sorted(vectors), 2):
        x, y = vectors[a], vectors[b]
        if len(x) == len(y) and round(dot(x, y) / math.sqrt(dot(x, x) * dot(y, y)), 6) > 0.3:
            want.add((a, b))
    got = graphs.embed_sim(spark, str(tmp_path), block_rows=11)
    rows = [(r["src"], r["dst"]) for r in got.collect()]
    assert len(rows) == len(set(rows)) and set(rows) == want and (40, 41) in want and (5, 7) in want
    assert "aggregate(" not in got._jdf.queryExecution().optimizedPlan().toString()  # no dot product row by row


def test_hash_bias_reads_the_orders(spark, small):
    got = QUERIES["hash_bias"](spark, small)
    n = spark.read.parquet(f"{small}/orders.parquet").count()
    assert {r["bit"]: r["flips"] for r in got.collect()} == dict.fromkeys(range(16), n)
    assert "orders.parquet" in "".join(got.inputFiles())


def test_simulation_constants_read_the_events(spark, small):
    got = QUERIES["sim_constants"](spark, small)
    ids = [r["event_id"] for r in spark.read.parquet(f"{small}/events.parquet").select("event_id").collect()]
    assert sorted(r["sim"] for r in got.collect()) == sorted(ids)
    assert "events.parquet" in "".join(got.inputFiles())
    xs = {r["sim"]: r["x"] for r in got.collect()}
    assert hashing.constant_list(spark, 5) == [xs[i] for i in range(5)]  # the same constants as those of the samplers


def test_sets_of_a_small_piece_are_expanded_at_once(monkeypatch):
    """A pass over few edges costs its calls, so a set of many vertices is expanded beside the others there."""
    rng = np.random.default_rng(3)
    n, m, sets = 60, 1500, np.arange(50)
    a, b = rng.integers(0, n, (2, m)).astype(np.int32)
    piece = rrlocal.Piece(n, a, b, rng.integers(-(1 << 31), 1 << 31, m).astype(np.int32), np.full(m, 90_000_000, np.int32), 31)
    want = sorted(zip(*(x.tolist() for x in piece.passed(sets, sets)), strict=True))
    assert len(want) > 20 * len(sets)
    monkeypatch.setattr(rrlocal.Piece, "passed", lambda *_: pytest.fail("a pass for each set"))
    assert sorted(zip(*(x.tolist() for x in piece.members(sets, sets)), strict=True)) == want


def roots_of(spark, g, sets):
    numbers = {r["number"]: r["id"] for r in rrset.numbered(g.vertices).collect()}
    drawn = spark.range(sets).select("id", hashing.hash31("id", 31).alias("q")).collect()
    return sorted((r["id"], numbers[r["q"] % len(numbers)]) for r in drawn)


def test_pieces_of_small_components_beyond_a_task_lose_no_set(spark, monkeypatch):
    """Several components share a piece that no task can hold."""
    g = CascadeGraph.of(spark.createDataFrame([(10 * i + j, 10 * i + j + 1, 1) for i in range(6) for j in range(3)], "src long, dst long, mult long"), 1.0)
    monkeypatch.setattr(rrset, "PIECE_EDGES", 8)
    want = sorted((r, 10 * (v // 10) + j) for r, v in roots_of(spark, g, 40) for j in range(4))
    assert sorted((r["rr_id"], r["id"]) for r in rrset.rr_sets(g, 40).collect()) == want


def test_pieces_are_packed_and_labelled_through_a_forest(spark, monkeypatch):
    """Labels of a graph with many edges and few vertices are solved in a task; a piece is a few rows, isolated roots included."""
    g = random_graph(spark, 40, 300, 8, 0.02)
    g = CascadeGraph(g.vertices.unionByName(spark.range(1000, 1005)).distinct(), g.edges.coalesce(1))
    want = sorted((r["rr_id"], r["id"]) for r in rrset.rr_sets(g, 80).collect())
    assert components.spanning(g.edges).count() < 40 and g.edges.count() > 200
    monkeypatch.setattr(rrset, "PIECE_EDGES", 100)
    monkeypatch.setattr(rrset, "components_star", lambda *_: pytest.fail("labels by contraction"))
    assert sorted((r["rr_id"], r["id"]) for r in rrset.rr_sets(g, 80).collect()) == want  # the component is beyond a task
    monkeypatch.setattr(rrset, "PIECE_EDGES", 1000)
    assert sorted((r["rr_id"], r["id"]) for r in rrset.rr_sets(CascadeGraph(g.vertices, g.edges.filter("src < 0")), 80).collect()) == roots_of(spark, g, 80)
    pieces = rrset.Pieces.of(g)
    rows = pieces.packs.collect()
    assert pieces.far is None and len(rows) < 10 and sum(len(r["a"]) for r in rows) == 4 * g.edges.count()
    flat = g.edges.select(F.lit(0).cast("int").alias("bucket"), F.lit(7).cast("long").alias("label"), "src", "dst", F.hash(F.col("h").cast("long")).alias("state"), "thr").toArrow()
    roots = pa.table({"rr_id": range(50), "id": [i % 43 for i in range(49)] + [1003]})
    monkeypatch.setattr(rrlocal, "STRIP", 64)  # several rows
    rows = rrlocal.packed(flat)
    shuffled = rows.take(pa.array(reversed(range(len(rows)))))
    pairs = [sorted(zip(*(x.column(c).to_pylist() for c in ("rr_id", "id")), strict=True)) for x in map(lambda e: rrlocal.solver(31)(roots, e), (flat, shuffled))]
    assert len(rows) == -(-len(flat) // 64) and pairs[0] == pairs[1]


def test_a_forest_is_held_within_a_bound(spark, monkeypatch):
    monkeypatch.setattr(components, "FOREST_EDGES", 8)
    edges = spark.createDataFrame([(i, j) for i in range(0, 60, 3) for j in (i + 1, i + 2, i + 30)], "src long, dst long").coalesce(1)
    labels = lambda e: sorted(map(tuple, components.components_local(e.select(F.lit(0).alias("sim"), "src", "dst")).collect()))
    assert labels(components.spanning(edges)) == labels(edges)
