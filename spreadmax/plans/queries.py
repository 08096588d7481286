"""The query catalogue: one entry per method, variant, baseline, measure or operator, with its SQL form where one exists."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadmax.functions import hashing, udfs
from spreadmax.operators import baselines, components, diffusion, gains, measures, rrset, sampling, selection, weights
from spreadmax.operators import graph as gr
from spreadmax.operators.graph import CascadeGraph
from spreadmax.plans import oracles as o
from spreadmax.plans import queue_sql as qs
from spreadmax.session import release, shared_dir, written
from spreadmax.sources import files, graphs
from spreadmax.streaming import edges as stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
R, P = 16, 0.01
T1, T01 = "21474836", "214748364"


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def _g(spark: SparkSession, d: str, name: str = "cust_part", w: float = P) -> CascadeGraph:
    return CascadeGraph.of(graphs.BUILDERS[name](spark, d), w)


def _memo(spark: SparkSession, d: str, name: str = "cust_part", w: float = P, runs: int = R, strategy: str = "local", sampler: str = "xor") -> gains.Memo:
    return gains.Memo.build(_g(spark, d, name, w), runs, strategy, sampler=sampler)


# --- graphs ---------------------------------------------------------------------------------------------------------

for _name in graphs.BUILDERS:
    query(f"graph_{_name}", f"WITH {o.EDGES[_name]} SELECT src, dst, mult FROM e")(
        lambda s, d, n=_name: graphs.BUILDERS[n](s, d)
    )

query(
    "graph_embed_sim",
    """WITH c AS (SELECT a.vec_id AS src, b.vec_id AS dst,
  round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS c
  FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id)
SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM c WHERE c > 0.3""",
)(lambda s, d: graphs.embed_sim(s, d).select("src", "dst"))


def _all_stats(s: SparkSession, d: str) -> DataFrame:
    out = None
    for n in sorted(graphs.BUILDERS):
        one = gr.graph_stats(graphs.BUILDERS[n](s, d), n).drop("mean_degree")
        out = one if out is None else out.unionByName(one)
    return out


def _stats_sql() -> str:
    parts = []
    for n in sorted(graphs.BUILDERS):
        parts.append(
            f"(WITH {o.EDGES[n]}, {o.DEG} SELECT '{n}' AS graph, (SELECT count(*) FROM dg) AS n, count(*) AS m, round(avg(mult), 6) AS avg_mult, "
            "round(count(*) / (SELECT count(*) FROM dg), 6) AS m_over_n, (SELECT max(d) FROM dg) AS max_deg FROM e)"
        )
    return "\nUNION ALL\n".join(parts)


query("graph_stats_all", _stats_sql())(_all_stats)
query("arcs_symmetrise", f"WITH {o.EDGES['cust_part']}, {o.ARCS} SELECT u, v FROM ar")(
    lambda s, d: gr.symmetrise(graphs.cust_part(s, d)).select("u", "v")
)
query("degrees", f"WITH {o.EDGES['cust_part']}, {o.DEG} SELECT id, d AS deg FROM dg")(lambda s, d: gr.degrees(graphs.cust_part(s, d)))
query(
    "induced_subgraph",
    f"WITH {o.EDGES['cust_part']}, k AS (SELECT 2 * c_custkey AS id FROM customer WHERE c_mktsegment = 'BUILDING' UNION ALL SELECT 2 * p_partkey + 1 FROM part) "
    "SELECT src, dst, mult FROM e WHERE src IN (SELECT id FROM k) AND dst IN (SELECT id FROM k)",
)(
    lambda s, d: gr.induced_subgraph(
        graphs.cust_part(s, d),
        graphs.load(s, d, "customer", "c_custkey", "c_mktsegment").filter("c_mktsegment = 'BUILDING'").select((2 * F.col("c_custkey")).alias("id"))
        .unionByName(graphs.load(s, d, "part", "p_partkey").select((2 * F.col("p_partkey") + 1).alias("id"))),
    )
)
query(
    "graph_between",
    "WITH raw AS (SELECT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey "
    "WHERE o_orderdate >= TIMESTAMP '1995-01-01' AND o_orderdate < TIMESTAMP '1996-01-01'), " + o._CANON + " SELECT src, dst, mult FROM e",
)(lambda s, d: graphs.graph_between(s, d, "1995-01-01", "1996-01-01"))
query(
    "graph_asof",
    "WITH ev AS (SELECT event_id, user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, ts FROM events), "
    "raw AS (SELECT user_id AS a, lag(user_id) OVER (PARTITION BY k ORDER BY ts, event_id) AS b FROM ev), " + o._CANON + " SELECT src, dst, mult FROM e",
)(graphs.graph_asof)

# --- hashes, draws --------------------------------------------------------------------------------------------------

_E2X = o.EDGES["cust_part"]
query("edge_hash_murmur",f"WITH {o.graph('cust_part')} SELECT src, dst, h FROM g")(
    lambda s, d: graphs.cust_part(s, d).select("src", "dst", hashing.edge_hash().cast("long").alias("h"))
)
query(
    "edge_hash_md5",
    f"WITH {o.EDGES['cust_part']} SELECT src, dst, CAST('0x' || substr(md5(src || '-' || dst), 1, 8) AS BIGINT) & 2147483647 AS h FROM e",
)(lambda s, d: graphs.cust_part(s, d).select("src", "dst", hashing.edge_hash(fn="md5").cast("long").alias("h")))
query("edge_hash_xx", f"WITH {_E2X}, {qs.xx64('zz', 'e', ['src', 'dst'])} SELECT src, dst, CAST(z & 2147483647 AS BIGINT) AS h FROM zz")(lambda s, d: graphs.cust_part(s, d).select("src", "dst", hashing.edge_hash(fn="xxhash64").cast("long").alias("h")))
query(
    "sim_constants",
    f"WITH ev AS (SELECT event_id AS sim FROM events WHERE event_id IS NOT NULL), {o.hash_ctes('s1', 'ev', ['7', 'sim'], 'x')} SELECT sim, CAST(x AS INT) AS x FROM s1",
)(lambda s, d: hashing.constants_of(graphs.load(s, d, "events", "event_id").select(F.col("event_id").cast("long").alias("sim"))))  # a simulation for each event
_DRAW = {
    "xor": f"{o.graph('user_key')},\n{o.sims(R)},\ndr AS (SELECT src, dst, sim, xor(h, x) AS d FROM g, sims)",
    "remix": f"{o.graph('user_key')},\n{o.sims(R)},\nhx AS (SELECT * FROM g, sims),\n{o.hash_ctes('dr', 'hx', ['h', 'x'], 'd')}",
}
for _s in ("xor", "remix"):
    query(f"draws_{_s}", f"WITH {_DRAW[_s]} SELECT src, dst, CAST(sim AS INT) AS sim, CAST(d AS INT) AS d FROM dr")(
        lambda s, d, k=_s: measures.draws(_g(s, d, "user_key"), R, sampler=k)
    )
    _cdf = (
        f"{_DRAW[_s]},\nbn AS (SELECT CAST(d // 134217728 AS INT) AS bin, count(*) AS n FROM dr GROUP BY 1),\n"
        "cd AS (SELECT bin, n, round(sum(n) OVER (ORDER BY bin) / (SELECT sum(n) FROM bn), 9) AS cdf FROM bn)"
    )
    query(f"draw_cdf_{_s}", f"WITH {_cdf} SELECT bin, n, cdf FROM cd")(lambda s, d, k=_s: measures.draw_cdf(_g(s, d, "user_key"), R, sampler=k))
    query(f"ks_uniform_{_s}", f"WITH {_cdf} SELECT round(max(abs(cdf - (bin + 1) / 16)), 6) AS ks FROM cd")(
        lambda s, d, k=_s: measures.ks_uniform(measures.draw_cdf(_g(s, d, "user_key"), R, sampler=k))
    )
    query(
        f"distinct_samples_{_s}",
        f"WITH {o.graph('geo_forest')}, {o.sampled(256, _s)}, "
        "ls AS (SELECT sim, string_agg(src || '-' || dst, ',' ORDER BY src, dst) AS edges FROM sampled GROUP BY sim) "
        "SELECT count(DISTINCT edges) + CAST(count(*) < 256 AS BIGINT) AS n_distinct FROM ls",
    )(lambda s, d, k=_s: measures.distinct_samples(sampling.fused_sample(_g(s, d, "geo_forest"), 256, sampler=k), 256))
    query(
        f"pair_cokeep_{_s}",
        f"WITH {o.graph('geo_forest')}, {o.sampled(256, _s)}, "
        "pr AS (SELECT a.src, a.dst, b.src AS s2, b.dst AS d2, count(*) AS n FROM sampled a JOIN sampled b ON a.sim = b.sim AND (a.src, a.dst) < (b.src, b.dst) GROUP BY ALL) "
        "SELECT count(*) AS pairs FROM pr WHERE n >= 2 AND n >= 1.28",
    )(lambda s, d, k=_s: measures.pair_cokeep(sampling.fused_sample(_g(s, d, "geo_forest"), 256, sampler=k), 256, P))
query(
    "hash_bias",
    "WITH k AS (SELECT o_custkey AS u, o_orderkey AS w, CAST(b AS INT) AS bit, xor(o_custkey, CAST(1 AS BIGINT) << b) AS f "
    "FROM orders, (SELECT range AS b FROM range(16)) WHERE o_custkey IS NOT NULL AND o_orderkey IS NOT NULL), "
    f"{o.hash_ctes('h1', 'k', ['u', 'w'], 'p')}, {o.hash_ctes('h2', 'h1', ['f', 'w'], 'q')} "
    "SELECT bit, count(*) AS flips, CAST(sum(bit_count(xor(p, q))) AS BIGINT) AS changed FROM h2 GROUP BY bit",
)(lambda s, d: measures.hash_bias(graphs.load(s, d, "orders", "o_custkey", "o_orderkey").select(F.col("o_custkey").alias("u"), F.col("o_orderkey").alias("v"))))

# --- weights --------------------------------------------------------------------------------------------------------


def _weighted(w) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        return CascadeGraph.of(graphs.cust_part(s, d), w()).edges.select("src", "dst", F.round("w", 9).alias("w"))

    return run


_E2 = o.EDGES["cust_part"]
query("weights_const_001", f"WITH {o.graph('cust_part')} SELECT src, dst, CAST(thr AS INT) AS thr FROM g")(
    lambda s, d: _g(s, d).edges.select("src", "dst", "thr")
)
query("weights_const_01", f"WITH {o.graph('cust_part', T01)} SELECT src, dst, CAST(thr AS INT) AS thr FROM g")(
    lambda s, d: _g(s, d, w=0.1).edges.select("src", "dst", "thr")
)
query("weights_uniform", f"WITH {_E2}, {o.hash_ctes('hw', 'e', ['src', 'dst', '11'], 'a')} SELECT src, dst, round(0.1 * (a / 2147483648.0), 9) AS w FROM hw")(
    _weighted(weights.uniform)
)
query(
    "weights_normal",
    f"WITH {_E2}, {o.hash_ctes('h1', 'e', ['src', 'dst', '11', '1'], 'a')}, {o.hash_ctes('h2', 'h1', ['src', 'dst', '11', '2'], 'b')} "
    "SELECT src, dst, round(greatest(0.0, least(1.0, 0.05 + 0.025 * sqrt(-2 * ln((a + 1) / 2147483649.0)) * cos(2 * pi() * (b / 2147483648.0)))), 9) AS w FROM h2",
)(_weighted(weights.gaussian))
query("weights_wc", f"WITH {_E2}, {o.DEG} SELECT u, v, round(1.0 / d, 9) AS w FROM ar JOIN dg ON id = v")(
    lambda s, d: weights.weighted_cascade(graphs.cust_part(s, d)).select("u", "v", F.round("w", 9).alias("w"))
)
query("weights_mult", f"WITH {o.EDGES['copurchase']} SELECT src, dst, round(1 - pow(0.99, mult), 9) AS w FROM e")(
    lambda s, d: graphs.copurchase(s, d).select("src", "dst", F.round(weights.strength(P), 9).alias("w"))
)

# --- sampling -------------------------------------------------------------------------------------------------------

_SAMPLE = "SELECT CAST(sim AS INT) AS sim, src, dst FROM sampled"
query("sample_edges", o.with_(o.graph("user_key"), o.sampled(R, "independent", 101), select=_SAMPLE))(
    lambda s, d: sampling.sample_edges(_g(s, d, "user_key"), R)
)
query("fused_sample", o.with_(o.graph("cust_part"), o.sampled(R), select=_SAMPLE))(lambda s, d: sampling.fused_sample(_g(s, d), R))
query("fused_sample_strict", o.with_(o.graph("cust_part"), o.sampled(R, op="<"), select=_SAMPLE))(
    lambda s, d: sampling.fused_sample(_g(s, d), R, strict=True)
)
query("fused_sample_remix", o.with_(o.graph("user_key"), o.sampled(R, "remix"), select=_SAMPLE))(
    lambda s, d: sampling.fused_sample(_g(s, d, "user_key"), R, sampler="remix")
)
query("kept_per_sim", o.with_(o.graph("cust_part"), o.sampled(R), select="SELECT CAST(sim AS INT) AS sim, count(*) AS kept FROM sampled GROUP BY sim"))(
    lambda s, d: sampling.fused_sample(_g(s, d), R).groupBy("sim").agg(F.count(F.lit(1)).alias("kept"))
)

# --- components, gains, selection -----------------------------------------------------------------------------------


def _superstep(s: SparkSession, d: str) -> DataFrame:
    g = _g(s, d)
    batches = components.batch_table(s, R, 8, 7)
    lanes = components.lanes_init(g, batches, 8)
    return components.lane_merge(lanes, components.lane_messages(lanes, g.arcs, batches, 8), 8)


_LANES = ", ".join(f"CAST(least(v.id, min(u) FILTER (sim = batch * 8 + {j})) AS BIGINT) AS l{j}" for j in range(8))
query(
    "lane_superstep",
    o.with_(
        o.graph("cust_part"), o.sampled(R), o.BOTH, f"bt AS (SELECT range AS batch FROM range({R // 8}))",
        select=f"SELECT v.id, CAST(batch AS INT) AS batch, {_LANES}, coalesce(bool_or(u < v.id), false) AS live "
        "FROM v CROSS JOIN bt LEFT JOIN arcs ON arcs.v = v.id AND arcs.sim // 8 = batch GROUP BY v.id, batch",
    ),
)(_superstep)

_COMPONENTS = o.with_(o.graph("cust_part"), o.sampled(R), o.MEMO, select="SELECT CAST(sim AS INT) AS sim, id, label FROM memo")
query("components_lanes", _COMPONENTS)(lambda s, d: components.components_lanes(_g(s, d), R, 8))
query("components_lanes_all", _COMPONENTS)(lambda s, d: components.components_lanes(_g(s, d), R, 16, push="all"))
query("components_lanes_pull", _COMPONENTS)(lambda s, d: components.components_lanes(_g(s, d), R, 16, push="pull"))
query("components_lanes_hybrid", _COMPONENTS)(lambda s, d: components.components_lanes(_g(s, d), R, 16, push="auto"))
query("components_sparse", _COMPONENTS)(lambda s, d: components.components(_g(s, d), R, "minlabel"))
query("components_star", _COMPONENTS)(lambda s, d: components.components(_g(s, d), R, "star"))
query("components_local", _COMPONENTS)(lambda s, d: components.components(_g(s, d), R, "local"))
query("components_waves", _COMPONENTS)(lambda s, d: components.components(_g(s, d), R, "local", wave=6))
query("components_auto", _COMPONENTS)(lambda s, d: components.components(_g(s, d), R, "auto"))
query(
    "components_critical",
    o.with_(o.graph("copurchase"), o.sampled(4), o.MEMO, select="SELECT CAST(sim AS INT) AS sim, id, label FROM memo"),
)(lambda s, d: components.components(_g(s, d, "copurchase"), 4, "star"))
_SIZES = o.with_(o.graph("cust_part"), o.sampled(R), o.MEMO, select="SELECT CAST(sim AS INT) AS sim, label, size FROM sizes")
query("component_sizes", _SIZES)(lambda s, d: gains.component_sizes(components.components(_g(s, d), R)))
query("size_histogram", o.with_(o.graph("cust_part"), o.sampled(R), o.MEMO, select="SELECT size, count(*) AS components FROM sizes GROUP BY size"))(
    lambda s, d: gains.size_histogram(gains.component_sizes(components.components(_g(s, d), R)))
)
query(
    "giant_share",
    o.with_(
        o.graph("cust_part", T01), o.sampled(R), o.MEMO,
        select="SELECT CAST(sim AS INT) AS sim, max(size) AS largest, round(max(size) / (SELECT count(*) FROM v), 6) AS share FROM sizes GROUP BY sim",
    ),
)(lambda s, d: (lambda g: gains.giant_share(gains.component_sizes(components.components(g, R)), g.vertices.count()))(_g(s, d, w=0.1)))
query(
    "giant_labels",
    o.with_(
        o.graph("cust_part"), o.sampled(R), o.MEMO,
        select="SELECT CAST(sim AS INT) AS sim, label, size FROM (SELECT *, row_number() OVER (PARTITION BY sim ORDER BY size DESC, label) AS k FROM sizes) WHERE k = 1",
    ),
)(lambda s, d: gains.giant_labels(gains.component_sizes(components.components(_g(s, d), R))))
query("initial_gains", o.with_(o.graph("cust_part"), o.sampled(R), o.MEMO, select=o.gains(R)))(
    lambda s, d: _memo(s, d).gains().select("id", "gain_sum")
)
query("initial_gains_remix", o.with_(o.graph("user_key"), o.sampled(R, "remix"), o.MEMO, select=o.gains(R)))(
    lambda s, d: _memo(s, d, "user_key", sampler="remix").gains().select("id", "gain_sum")
)
query("first_seed", o.seeds_sql("cust_part", R, 1))(lambda s, d: selection.select_lazy(_memo(s, d), 1).frame(s))


def _marginal(s: SparkSession, d: str) -> DataFrame:
    m = _memo(s, d)
    seeds = s.createDataFrame([(0,), (1,)], "id long")
    return gains.marginal_gains(m.vertices, m.rows, gains.covered_by(m.rows, seeds), seeds, R)


query(
    "marginal_gain_given",
    o.with_(
        o.graph("cust_part"), o.sampled(R), o.MEMO, "sd AS (SELECT 0 AS id UNION ALL SELECT 1)",
        "cv AS MATERIALIZED (SELECT DISTINCT sim, label FROM ms WHERE id IN (SELECT id FROM sd))", select=o.gains(R, "cv", "sd"),
    ),
)(_marginal)

_SEEDS = o.seeds_sql("cust_part", R, 5)
query("seeds_scan", _SEEDS)(lambda s, d: selection.select_scan(_memo(s, d), 5).frame(s))
query("seeds_lazy", _SEEDS)(lambda s, d: selection.select_lazy(_memo(s, d), 5, block=64).frame(s))
query("seeds_lookahead", _SEEDS)(lambda s, d: selection.select_lazy(_memo(s, d), 5, lookahead=True).frame(s))
query("seeds_refresh", o.seeds_sql("cust_part", 8, 3, T01))(lambda s, d: selection.select_refresh(_memo(s, d, w=0.1, runs=8), 3).frame(s))
query("fused_memo_greedy", _SEEDS)(lambda s, d: flagship(s, d))
query("fused_memo_lanes", o.seeds_sql("geo_forest", R, 5, T01))(lambda s, d: selection.select_lazy(_memo(s, d, "geo_forest", 0.1, strategy="lanes"), 5).frame(s))
query("fused_memo_part_supp", o.seeds_sql("part_supp", 8, 5))(lambda s, d: selection.select_refresh(_memo(s, d, "part_supp", runs=8), 5).frame(s))
query("fused_memo_cust_supp", o.seeds_sql("cust_supp", 8, 5))(lambda s, d: selection.select_refresh(_memo(s, d, "cust_supp", runs=8), 5).frame(s))


def flagship(s: SparkSession, d: str, k: int = 5, runs: int = R) -> DataFrame:
    """The proposed method end to end: hashes, fused samples, components, gains, lazy selection."""
    return selection.select_refresh(_memo(s, d, runs=runs, strategy="auto"), k).frame(s)


def _memo_reopened(s: SparkSession, d: str) -> DataFrame:
    import uuid

    place = f"{shared_dir(s)}/spreadmax/saved-{uuid.uuid4().hex}"
    _memo(s, d).save(place)
    return selection.select_lazy(gains.Memo.load(s, place), 5).frame(s)


query("memo_save_load", _SEEDS)(_memo_reopened)
query(
    "fused_greedy",
    f"SELECT rank, id, gain_sum FROM ({o.seeds_sql('geo_forest', 4, 3, T01)})",
)(lambda s, d: baselines.fused_greedy(_g(s, d, "geo_forest", 0.1), 3, 4).frame(s).select("rank", "id", "gain_sum"))

# --- diffusion ------------------------------------------------------------------------------------------------------

_START = f"st AS (SELECT sim, id FROM (SELECT range AS sim FROM range({R})), (SELECT 1 AS id UNION ALL SELECT 5))"


def _seeds(s: SparkSession) -> DataFrame:
    return s.createDataFrame([(1,), (5,)], "id long")  # two nations of geo_forest


_ROUNDS = "SELECT CAST(sim AS INT) AS sim, CAST(id AS BIGINT) AS id, CAST(round AS INT) AS round FROM r"
_COUNTS = "SELECT CAST(sim AS INT) AS sim, count(*) AS reached FROM r GROUP BY sim"
query("reach_of_seeds", o.with_(o.graph("geo_forest", T01), o.sampled(R), o.BOTH, _START, o.reach("arcs", "st"), select=_ROUNDS))(
    lambda s, d: diffusion.reach_fixed_draws(_g(s, d, "geo_forest", 0.1), _seeds(s), R)
)
query("spread_fixed_draws", o.with_(o.graph("geo_forest", T01), o.sampled(R), o.BOTH, _START, o.reach("arcs", "st"), select=_COUNTS))(
    lambda s, d: diffusion.reached_per_sim(diffusion.reach_fixed_draws(_g(s, d, "geo_forest", 0.1), _seeds(s), R))
)
_IND = (o.graph("geo_forest", T01), o.sampled(R, "independent", 101), o.BOTH, _START, o.reach("arcs", "st"))
query("spread_ic_rounds", o.with_(*_IND, select=_ROUNDS))(lambda s, d: diffusion.cascade_rounds(_g(s, d, "geo_forest", 0.1), _seeds(s), R))
query("spread_ic", o.with_(*_IND, select=_COUNTS))(lambda s, d: diffusion.spread_mc(_g(s, d, "geo_forest", 0.1), _seeds(s), R))
query(
    "score_seeds",
    o.with_(*_IND, select=f"SELECT round(avg(n), 6) AS sigma, round(stddev_samp(n) / sqrt({R}), 6) AS se FROM (SELECT count(*) AS n FROM r GROUP BY sim)"),
)(lambda s, d: diffusion.score_seeds(_g(s, d, "geo_forest", 0.1), _seeds(s), R))
_WC = (
    o.EDGES["geo_forest"], o.DEG, f"si AS (SELECT range AS sim FROM range({R}))", "wx AS (SELECT u, v, d, sim FROM ar JOIN dg ON id = v, si)",
    o.hash_ctes("wh", "wx", ["u", "v", "sim", "101"], "q"), "wa AS MATERIALIZED (SELECT sim, u, v FROM wh WHERE q * d <= 2147483647)", _START,
)
query("spread_wc", o.with_(*_WC, o.reach("wa", "st"), select=_COUNTS))(lambda s, d: diffusion.spread_mc(_g(s, d, "geo_forest", 0.1), _seeds(s), R, "wc"))
_LT = (
    o.EDGES["geo_forest"], o.DEG, f"si AS (SELECT range AS sim FROM range({R}))", "tx AS (SELECT id AS w, d, sim FROM dg, si)",
    o.hash_ctes("th", "tx", ["w", "sim", "101"], "q"),
)
query(
    "spread_lt_live_edge",
    o.with_(
        *_LT, "nb AS (SELECT u, v, row_number() OVER (PARTITION BY v ORDER BY u) AS k FROM ar)",
        "la AS MATERIALIZED (SELECT sim, u, v FROM nb JOIN th ON w = v WHERE q * d >= (k - 1) * 2147483648 AND q * d < k * 2147483648)", _START,
        o.reach("la", "st"), select=_COUNTS,
    ),
)(lambda s, d: diffusion.spread_mc(_g(s, d, "geo_forest", 0.1), _seeds(s), R, "lt_live"))


def _lt_rounds(rounds: int = 6) -> str:
    parts = [*_LT, "th2 AS MATERIALIZED (SELECT sim, w, d, q FROM th)", _START, "a0 AS MATERIALIZED (SELECT sim, id FROM st)"]
    for k in range(1, rounds + 1):
        parts.append(
            f"a{k} AS MATERIALIZED (SELECT sim, id FROM a{k - 1} UNION SELECT a.sim, ar.v FROM a{k - 1} a JOIN ar ON ar.u = a.id "
            f"JOIN th2 ON th2.sim = a.sim AND th2.w = ar.v GROUP BY a.sim, ar.v, th2.q, th2.d HAVING count(*) * 2147483647 > th2.q * th2.d)"
        )
    return o.with_(*parts, select=f"SELECT CAST(sim AS INT) AS sim, count(*) AS reached FROM a{rounds} GROUP BY sim")


query("spread_lt", _lt_rounds())(lambda s, d: diffusion.spread_mc(_g(s, d, "geo_forest", 0.1), _seeds(s), R, "lt"))
query(
    "spread_forest_exact",
    o.with_(
        o.EDGES["geo_forest"], o.ARCS,
        "pth(a, b, came, pr) AS (SELECT id, id, CAST(-1 AS BIGINT), CAST(1.0 AS DOUBLE) FROM (SELECT DISTINCT u AS id FROM ar) UNION ALL "
        "SELECT a, v, b, pr * 0.1 FROM pth JOIN ar ON u = b WHERE v <> came)",
        select="SELECT a AS id, round(sum(pr), 6) AS sigma FROM pth GROUP BY a",
    ),
)(lambda s, d: diffusion.forest_exact(graphs.geo_forest(s, d), lambda c: F.pmod(c, F.lit(4)), 0.1))


def _toy(s: SparkSession, w: float = 0.3) -> CascadeGraph:
    return CascadeGraph.of(graphs.cycle_of_friends(s), w)


_STATES = (
    o.EDGES["toy"], "en AS (SELECT src, dst, row_number() OVER (ORDER BY src, dst) - 1 AS k FROM e)",
    "sx AS (SELECT range AS sim FROM range(1024))",
    "px AS (SELECT sim, pow(0.3, bit_count(sim)) * pow(0.7, 10 - bit_count(sim)) AS prob FROM sx)",
    "sampled AS MATERIALIZED (SELECT sim, src, dst FROM sx, en WHERE (sim >> k) & 1 = 1)", o.BOTH,
    "pz AS (SELECT a.range AS x, b.range AS y FROM range(1, 6) a, range(1, 6) b WHERE a.range < b.range)",
)
_EXACT = "(SELECT s AS set, round(sum(n * prob), 6) AS sigma FROM (SELECT s, sim, count(*) AS n FROM r GROUP BY ALL) JOIN px USING (sim) GROUP BY s)"
query(
    "spread_enumerated",
    o.with_(
        *_STATES, "st AS (SELECT CAST(range AS VARCHAR) AS s, sim, range AS id FROM range(1, 6), sx)", o.reach("ax", "st", "s, sim").replace("JOIN ax a", "JOIN (SELECT DISTINCT t.s, arcs.* FROM arcs, (SELECT DISTINCT s FROM st) t) a"),
        select=f"SELECT * FROM {_EXACT}",
    ),
)(lambda s, d: diffusion.spread_exact(_toy(s).edges, s.createDataFrame([(str(i), i) for i in range(1, 6)], "set string, id long")))
query(
    "optimal_seeds",
    o.with_(
        *_STATES, "st AS (SELECT x || '-' || y AS s, sim, x AS id FROM pz, sx UNION ALL SELECT x || '-' || y, sim, y FROM pz, sx)",
        o.reach("ax", "st", "s, sim").replace("JOIN ax a", "JOIN (SELECT DISTINCT t.s, arcs.* FROM arcs, (SELECT DISTINCT s FROM st) t) a"),
        select=f"SELECT * FROM {_EXACT} ORDER BY sigma DESC, set LIMIT 1",
    ),
)(lambda s, d: diffusion.optimal_seeds(_toy(s).edges, 2))

# --- baselines ------------------------------------------------------------------------------------------------------


def _frame(s: SparkSession, out: selection.Selection) -> DataFrame:
    rows = [(i + 1, v, float(x)) for i, (v, x) in enumerate(out.seeds)]
    return s.createDataFrame(rows, "rank int, id long, gain double")


query("plain_greedy", qs.plain("geo_forest", T01, R, 2))(lambda s, d: _frame(s, baselines.plain_greedy(_g(s, d, "geo_forest", 0.1), 2, R)))
query("lazy_forward", qs.lazy("geo_forest", T01, R, 2))(lambda s, d: _frame(s, baselines.lazy_forward(_g(s, d, "geo_forest", 0.1), 2, R)))
query("lazy_forward_lookahead", qs.lazy("geo_forest", T01, R, 2))(
    lambda s, d: _frame(s, baselines.lazy_forward(_g(s, d, "geo_forest", 0.1), 2, R, lookahead=True))
)


def _component_sql() -> str:
    first = o.with_(
        o.graph("geo_forest", T01), o.sampled(R, "independent", 101), o.MEMO, f"g1 AS ({o.gains(R)})",
        select=f"SELECT 1 AS rank, id, gain_sum / {R} AS gain FROM g1 ORDER BY gain_sum DESC, id LIMIT 1",
    )
    second = o.with_(
        o.graph("geo_forest", T01), o.sampled(R, "independent", 102), o.MEMO, f"sd AS (SELECT id FROM ({first}))",
        "cv AS MATERIALIZED (SELECT DISTINCT sim, label FROM ms WHERE id IN (SELECT id FROM sd))", f"g2 AS ({o.gains(R, 'cv', 'sd')})",
        select=f"SELECT 2 AS rank, id, gain_sum / {R} AS gain FROM g2 ORDER BY gain_sum DESC, id LIMIT 1",
    )
    return f"SELECT CAST(rank AS INT) AS rank, id, round(gain, 6) AS gain FROM (({first}) UNION ALL ({second}))"


query("component_greedy", _component_sql())(lambda s, d: _frame(s, baselines.component_greedy(_g(s, d, "geo_forest", 0.1), 2, R)))
query("hybrid_lazy_greedy", qs.lazy("geo_forest", T01, R, 3))(lambda s, d: _frame(s, baselines.hybrid_lazy_greedy(_g(s, d, "geo_forest", 0.1), 3, R)))

_RR = (
    o.graph("supp_supp"), "nv AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY id % 64, id) - 1 AS number FROM v)",
    "ids AS (SELECT range AS rr_id FROM range(200))", o.hash_ctes("ih", "ids", ["rr_id", "31"], "q"),
    "st AS MATERIALIZED (SELECT rr_id, id FROM ih JOIN nv ON number = q % (SELECT count(*) FROM nv))",
    "rx AS (SELECT src, dst, h, thr, rr_id FROM g, ids)", o.hash_ctes("rh", "rx", ["h", "rr_id", "31"], "w"),
    "rs AS MATERIALIZED (SELECT rr_id, src, dst FROM rh WHERE w <= thr)",
    "ra AS MATERIALIZED (SELECT rr_id, src AS u, dst AS v FROM rs UNION ALL SELECT rr_id, dst, src FROM rs)", o.reach("ra", "st", "rr_id"),
    "rr AS MATERIALIZED (SELECT rr_id, id FROM r)",
)
query("rr_sets", o.with_(*_RR, select="SELECT rr_id, id FROM rr"))(lambda s, d: rrset.rr_sets(_g(s, d, "supp_supp"), 200))


def _rr_cover(s: SparkSession, d: str) -> DataFrame:
    seeds, _ = rrset.greedy_cover(written(rrset.rr_sets(_g(s, d, "supp_supp"), 200), "rr"), 3)
    return s.createDataFrame([(i + 1, v, n) for i, (v, n) in enumerate(seeds)], "rank int, id long, covered long")


def _cover_sql(k: int = 3) -> str:
    parts, before = [*_RR], "rr"
    for i in range(1, k + 1):
        parts.append(f"b{i} AS MATERIALIZED (SELECT {i} AS rank, id, count(*) AS covered FROM {before} GROUP BY id ORDER BY 3 DESC, 2 LIMIT 1)")
        parts.append(f"rr{i} AS MATERIALIZED (SELECT * FROM {before} WHERE rr_id NOT IN (SELECT rr_id FROM {before} WHERE id IN (SELECT id FROM b{i})))")
        before = f"rr{i}"
    union = " UNION ALL ".join(f"SELECT * FROM b{i}" for i in range(1, k + 1))
    return o.with_(*parts, select=f"SELECT CAST(rank AS INT) AS rank, id, covered FROM ({union})")


query("rr_cover", _cover_sql())(_rr_cover)


def _rrset(eps: float, most: int | None = None) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        edges = written(graphs.supp_supp(s, d), "edges")  # read for the vertices, the components and the sets
        got = rrset.rrset_greedy(CascadeGraph.of(edges, 0.002), 2, eps, most=most)
        release(edges)
        return s.createDataFrame([(i + 1, v, n, got["sets"]) for i, (v, n) in enumerate(got["seeds"])], "rank int, id long, covered long, sets long")

    return run


_T0002 = str(math.floor(0.002 * 2147483647))
query("rrset_greedy_05", qs.rrset("supp_supp", _T0002, 2, 0.5, 6))(_rrset(0.5))
query("rrset_greedy_013", qs.rrset("supp_supp", _T0002, 2, 0.13, 6))(_rrset(0.13))
query("degree_seeds", f"WITH {_E2}, {o.DEG} SELECT CAST(row_number() OVER (ORDER BY d DESC, id) AS INT) AS rank, id, d AS deg FROM dg ORDER BY d DESC, id LIMIT 5")(
    lambda s, d: baselines.degree_seeds(graphs.cust_part(s, d), 5)
)
query(
    "random_seeds",
    f"WITH {o.graph('cust_part')}, {o.hash_ctes('vh', 'v', ['id', '5'], 'q')} SELECT CAST(row_number() OVER (ORDER BY q, id) AS INT) AS rank, id FROM vh ORDER BY q, id LIMIT 5",
)(lambda s, d: baselines.random_seeds(gr.vertices_of(graphs.cust_part(s, d)), 5))

# --- measures and relational operators ------------------------------------------------------------------------------

_G5 = f"({_SEEDS})"


def _submodular(s: SparkSession, d: str) -> DataFrame:
    seeds = flagship(s, d)
    drop = F.lag("gain_sum").over(Window.orderBy("rank")) - F.col("gain_sum")
    return seeds.select("rank", "gain_sum", F.coalesce(drop, F.lit(0)).alias("loss"), (F.coalesce(drop, F.lit(0)) >= 0).alias("holds"))


query(
    "submodularity_check",
    f"SELECT rank, gain_sum, coalesce(lag(gain_sum) OVER (ORDER BY rank) - gain_sum, 0) AS loss, coalesce(lag(gain_sum) OVER (ORDER BY rank) - gain_sum, 0) >= 0 AS holds FROM {_G5}",
)(_submodular)


def _visits(s: SparkSession, d: str) -> DataFrame:
    rows = []
    edges = written(graphs.cust_part(s, d), "edges")  # both weights share them
    for w in (0.01, 0.1):
        m = gains.Memo.build(CascadeGraph.of(edges, w), 8, "local")
        for kind, f in (("lazy", selection.select_lazy), ("refresh", selection.select_refresh)):
            out = f(m, 5)
            rows.append((kind, w, out.visits, out.scans))
        m.release()
    release(edges)
    return s.createDataFrame(rows, "method string, p double, visits long, scans long")


query("lazy_visits", f"({qs.visits('cust_part', T1, 0.01, 8, 5)}) UNION ALL ({qs.visits('cust_part', T01, 0.1, 8, 5)})")(_visits)


def _trace(s: SparkSession, d: str) -> DataFrame:
    rows = []
    for push in ("live", "all"):
        t = components.Trace()
        components.components_lanes(_g(s, d), R, 16, push=push, trace=t)
        rows += [(push, r["round"], r["live"], r["arcs_visited"]) for r in t.rounds]
    return s.createDataFrame(rows, "push string, round int, live long, arcs_visited long")


query("frontier_trace", qs.trace("cust_part", T1, R))(_trace)


def _toy_trace(s: SparkSession, d: str) -> DataFrame:
    memo = components.components_minlabel(graphs.toy_samples(s))
    m = gains.Memo.of(s.range(1, 6).select("id"), memo, 2)
    return selection.select_lazy(m, 2).frame(s)


query("toy_example", "SELECT * FROM (VALUES (CAST(1 AS INT), CAST(1 AS BIGINT), CAST(9 AS BIGINT), CAST(9 AS BIGINT)), (2, 2, 1, 10)) t(rank, id, gain_sum, sigma_sum)")(_toy_trace)
query(
    "seed_jaccard",
    f"WITH a AS (SELECT id FROM {_G5}), dd AS (WITH {_E2}, {o.DEG} SELECT id FROM dg ORDER BY d DESC, id LIMIT 5), "
    "c AS (SELECT count(*) AS common FROM (SELECT id FROM a INTERSECT SELECT id FROM dd)), t AS (SELECT count(*) AS either FROM (SELECT id FROM a UNION SELECT id FROM dd)) "
    "SELECT common, either, round(common / either, 6) AS jaccard FROM c, t",
)(lambda s, d: measures.jaccard(flagship(s, d), baselines.degree_seeds(graphs.cust_part(s, d), 5)))


def _runs(s: SparkSession, d: str) -> DataFrame:
    from spreadmax.plans.workloads import experiment

    return experiment(s, d, ["geo_forest", "user_key"], ["c001", "c01"], ["fused_memo", "degree"], k=3, runs=R, score_runs=64)


def _runs_sql() -> str:
    parts = []
    for g in ("geo_forest", "user_key"):
        for w, thr in (("c001", T1), ("c01", T01)):
            top = f"WITH {o.EDGES[g]}, {o.DEG} SELECT id FROM dg ORDER BY d DESC, id LIMIT 3"
            for m, seeds in (("fused_memo", f"SELECT id FROM ({o.seeds_sql(g, R, 3, thr)})"), ("degree", top)):
                parts.append(f"SELECT '{g}' AS graph, '{w}' AS setting, '{m}' AS method, sigma AS score, se AS score_se FROM ({qs.score(g, thr, seeds, 64)})")
    return " UNION ALL ".join(parts)


_RUNS = f"rn AS MATERIALIZED ({_runs_sql()})"
query(
    "report_cube",
    f"WITH {_RUNS} SELECT graph, setting, method, round(avg(score), 4) AS score, count(*) AS n, grouping(graph, setting, method) AS level FROM rn GROUP BY CUBE (graph, setting, method)",
)(lambda s, d: measures.report_cube(_runs(s, d)))
query(
    "report_pivot",
    f"WITH {_RUNS} SELECT graph, round(max(score) FILTER (method = 'degree' AND setting = 'c001'), 4) AS degree_c001, round(max(score) FILTER (method = 'degree' AND setting = 'c01'), 4) AS degree_c01, "
    "round(max(score) FILTER (method = 'fused_memo' AND setting = 'c001'), 4) AS fused_memo_c001, round(max(score) FILTER (method = 'fused_memo' AND setting = 'c01'), 4) AS fused_memo_c01 FROM rn GROUP BY graph",
)(lambda s, d: measures.report_pivot(_runs(s, d)))
_GAINS = o.with_(o.graph("cust_part"), o.sampled(R), o.MEMO, select=o.gains(R))
query("gains_rank_window", f"SELECT id, gain_sum, CAST(rank() OVER (ORDER BY gain_sum DESC) AS INT) AS rk, CAST(dense_rank() OVER (ORDER BY gain_sum DESC) AS INT) AS dr FROM ({_GAINS})")(
    lambda s, d: measures.gain_ranks(_memo(s, d).gains().select("id", "gain_sum"))
)


def _per_nation(s: SparkSession, d: str) -> DataFrame:
    top = Window.partitionBy("c_nationkey").orderBy(F.desc("gain_sum"), "id")
    cust = graphs.load(s, d, "customer", "c_custkey", "c_nationkey").select((2 * F.col("c_custkey")).alias("id"), "c_nationkey")
    return _memo(s, d).gains().join(cust, "id").withColumn("k", F.row_number().over(top)).filter("k <= 2").select("c_nationkey", "k", "id", "gain_sum")


query(
    "gains_topk_per_nation",
    f"SELECT c_nationkey, CAST(k AS INT) AS k, id, gain_sum FROM (SELECT c_nationkey, id, gain_sum, row_number() OVER (PARTITION BY c_nationkey ORDER BY gain_sum DESC, id) AS k "
    f"FROM ({_GAINS}) JOIN customer ON id = 2 * c_custkey) WHERE k <= 2",
)(_per_nation)
query("sigma_running", f"SELECT rank, id, gain_sum, sigma_sum FROM {_G5}")(lambda s, d: gains.running_sigma(flagship(s, d).drop("sigma_sum")))
query(
    "draw_ntile",
    f"WITH {_DRAW['xor']}, q AS (SELECT d, ntile(4) OVER (ORDER BY d, src, dst, sim) AS tile FROM dr) SELECT CAST(tile AS INT) AS tile, count(*) AS n, CAST(max(d) AS INT) AS top FROM q GROUP BY tile",
)(lambda s, d: measures.draw_tiles(measures.draws(_g(s, d, "user_key"), R), 4))
query("approx_reach")(lambda s, d: _memo(s, d).rows.agg(F.approx_count_distinct("id").alias("reached"), F.percentile_approx("size", 0.5).alias("median_size")))
query(
    "setops_seeds",
    f"WITH a AS (SELECT id FROM {_G5}), dd AS (WITH {_E2}, {o.DEG} SELECT id FROM dg ORDER BY d DESC, id LIMIT 5) "
    "SELECT 'only_memo' AS part, id FROM (SELECT id FROM a EXCEPT SELECT id FROM dd) UNION ALL SELECT 'only_degree', id FROM (SELECT id FROM dd EXCEPT SELECT id FROM a)",
)(
    lambda s, d: (lambda a, b: a.subtract(b).select(F.lit("only_memo").alias("part"), "id").union(b.subtract(a).select(F.lit("only_degree").alias("part"), "id")))(
        flagship(s, d).select("id"), baselines.degree_seeds(graphs.cust_part(s, d), 5).select("id")
    )
)

# --- sources, SQL surface, streams ----------------------------------------------------------------------------------


def _csv_roundtrip(s: SparkSession, d: str) -> DataFrame:
    import uuid

    place = f"{shared_dir(s)}/spreadmax/edges-{uuid.uuid4().hex}"
    graphs.cust_part(s, d).select("src", "dst", F.lit(0.01).alias("w")).write.csv(place, sep="\t")
    return files.read_edges(s, place)


query("edges_csv_roundtrip", f"WITH {_E2} SELECT src, dst, CAST(0.01 AS DOUBLE) AS w FROM e")(_csv_roundtrip)
query("edges_json_props", "SELECT 2 * user_id AS src, 2 * CAST(json_extract(props, '$.k') AS BIGINT) + 1 AS dst FROM events")(
    lambda s, d: graphs.interactions(s, d).select("src", "dst")
)


def _sql_surface(s: SparkSession, d: str) -> DataFrame:
    hashing.register_sql(s)
    _g(s, d).register("q")
    x = hashing.constant_list(s, 1)[0]
    return s.sql(f"SELECT src, dst, edge_hash(src, dst) AS h FROM q_edges WHERE kept(edge_hash(src, dst), {x}, threshold(0.01D))")


query("sql_functions", o.with_(o.graph("cust_part"), o.sampled(1), select="SELECT g.src, g.dst, CAST(h AS INT) AS h FROM g JOIN sampled USING (src, dst)"))(_sql_surface)


def _udtf(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    sampling.fused_sample(_g(s, d), R).createOrReplaceTempView("q_sampled")
    return s.sql("SELECT sim, id, label FROM component_labels(TABLE(q_sampled) PARTITION BY sim)")


query("udtf_components", _COMPONENTS)(_udtf)


def _lane_min(s: SparkSession, d: str) -> DataFrame:
    g = _g(s, d)
    sides = g.arcs.select("v", F.array("u", F.col("v")).alias("lanes"))
    return sides.groupBy(F.col("v").alias("id")).agg(udfs.lane_min("lanes").alias("m")).select("id", F.get("m", F.lit(0)).alias("least"))


query("udf_lane_min", f"WITH {_E2}, {o.ARCS} SELECT v AS id, min(u) AS least FROM ar GROUP BY v")(_lane_min)


def _memory(s: SparkSession, d: str) -> DataFrame:
    flagship(s, d).count()
    return measures.memory_report(s)


query("memory_report")(_memory)


def _cosine(s: SparkSession, d: str) -> DataFrame:
    v = graphs.load(s, d, "embeddings", "vec_id", "embedding")
    a = v.select(F.col("vec_id").alias("a"), F.col("embedding").alias("ea"))
    b = v.select((F.col("vec_id") + 1).alias("a"), F.col("embedding").alias("eb"))
    return a.join(b, "a").select(F.col("a").alias("vec_id"), F.round(udfs.cosine("ea", "eb"), 6).alias("cosine"))


query(
    "udf_cosine",
    "SELECT a.vec_id, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cosine FROM embeddings a JOIN embeddings b ON a.vec_id = b.vec_id + 1",
)(_cosine)
_EV = "ev AS (SELECT 2 * user_id AS src, 2 * CAST(json_extract(props, '$.k') AS BIGINT) + 1 AS dst, ts FROM events)"
_CLOSED = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"  # the watermark: later windows are not closed yet
query(
    "stream_edges_windowed",
    f"WITH {_EV} SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, src, dst, count(*) AS mult FROM ev WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= {_CLOSED} GROUP BY ALL",
)(
    lambda s, d: stream.drained(stream.windowed_edges(stream.edge_stream(s, d))).withColumn("start", F.col("start").cast("timestamp_ntz"))
)
query(
    "stream_session",
    f"WITH {_EV}, nx AS (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY src, dst ORDER BY ts) + INTERVAL 1 DAY OR lag(ts) OVER (PARTITION BY src, dst ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS nw FROM ev), "
    "gp AS (SELECT *, sum(nw) OVER (PARTITION BY src, dst ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM nx) "
    f"SELECT CAST(min(ts) AS TIMESTAMP) AS start, src, dst, count(*) AS mult FROM gp GROUP BY src, dst, s HAVING max(ts) + INTERVAL 1 DAY <= {_CLOSED}",
)(lambda s, d: stream.drained(stream.windowed_edges(stream.edge_stream(s, d), "session")).withColumn("start", F.col("start").cast("timestamp_ntz")))
query("stream_degree", f"WITH {_EV} SELECT id, count(*) AS interactions FROM (SELECT unnest([src, dst]) AS id FROM ev) GROUP BY id")(
    lambda s, d: stream.latest(stream.running_degree(stream.edge_stream(s, d)), ["id"])
)
query(
    "stream_sliding",
    f"WITH {_EV}, sl AS (SELECT src, dst, time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 12 HOUR AS start FROM ev, (VALUES (0), (1)) t(k)) "
    f"SELECT CAST(start AS TIMESTAMP) AS start, src, dst, count(*) AS mult FROM sl WHERE start + INTERVAL 1 DAY <= {_CLOSED} GROUP BY ALL",
)(lambda s, d: stream.drained(stream.windowed_edges(stream.edge_stream(s, d), "sliding")).withColumn("start", F.col("start").cast("timestamp_ntz")))
query("stream_dedup", f"WITH {_EV} SELECT DISTINCT src, dst FROM ev")(
    lambda s, d: stream.drained(stream.dedup_edges(stream.edge_stream(s, d)).select("src", "dst")).distinct()
)
query("stream_memo", o.with_(o.graph("user_key"), o.sampled(8), o.MEMO, select="SELECT CAST(sim AS INT) AS sim, id, label FROM memo"))(
    lambda s, d: stream.stream_memo(s, d, P, 8)
)


query("experiment_scores", f"WITH {_RUNS} SELECT graph, setting, method, score, score_se FROM rn")(
    lambda s, d: _runs(s, d).select("graph", "setting", "method", "score", "score_se")
)


def _ratio(s: SparkSession, d: str) -> DataFrame:
    from spreadmax.plans.experiments import ratio

    return ratio(s, d)


query("approx_ratio")(_ratio)
assert math.isclose(math.floor(0.01 * 2147483647), int(T1))
