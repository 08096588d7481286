"""SQL forms of the queries: independent statements over the given tables, checked by another engine.

Murmur3 of BIGINT columns is spelled out step by step, one common table
expression each, so that no expression grows.
"""

from __future__ import annotations

INT_MAX = 2147483647
M = 4294967296


def hash_steps(parts: list[str], out: str = "h") -> list[str]:
    """SELECTs, each over the one before (@), that add column `out`: the 31-bit Murmur3 of the BIGINT `parts`."""
    steps = ["SELECT *, CAST(42 AS UBIGINT) AS _s, CAST(0 AS UBIGINT) AS _k FROM @"]
    for p in parts:
        for half in (f"CAST(({p}) & 4294967295 AS UBIGINT)", f"CAST((({p}) >> 32) & 4294967295 AS UBIGINT)"):
            steps += [
                f"SELECT * REPLACE (({half} * 3432918353) % {M} AS _k) FROM @",
                f"SELECT * REPLACE ((((_k * 32768) % {M} + (_k >> 17)) * 461845907) % {M} AS _k) FROM @",
                "SELECT * REPLACE (xor(_s, _k) AS _s) FROM @",
                f"SELECT * REPLACE ((((_s * 8192) % {M} + (_s >> 19)) * 5 + 3864292196) % {M} AS _s) FROM @",
            ]
        steps += [
            "SELECT * REPLACE (xor(_s, CAST(8 AS UBIGINT)) AS _s) FROM @",
            f"SELECT * REPLACE ((xor(_s, _s >> 16) * 2246822507) % {M} AS _s) FROM @",
            f"SELECT * REPLACE ((xor(_s, _s >> 13) * 3266489909) % {M} AS _s) FROM @",
            "SELECT * REPLACE (xor(_s, _s >> 16) AS _s) FROM @",
        ]
    return [*steps, f"SELECT * EXCLUDE (_s, _k), CAST(_s & {INT_MAX} AS BIGINT) AS {out} FROM @"]


def chained(name: str, source: str, steps: list[str]) -> str:
    """The steps as common table expressions; the last one is `name`."""
    text, before = [], source
    for i, step in enumerate(steps):
        own = name if i == len(steps) - 1 else f"{name}_{i}"
        text.append(f"{own} AS ({step.replace('@', before)})")
        before = own
    return ",\n".join(text)


def nested(source: str, steps: list[str]) -> str:
    """The steps as subqueries of one SELECT over the query `source`."""
    for step in steps:
        source = step.replace("@", f"({source})")
    return source


def hash_ctes(name: str, source: str, parts: list[str], out: str = "h") -> str:
    """CTEs that add column `out` (31-bit Murmur3 of the BIGINT `parts`) to `source`; the last one is `name`."""
    return chained(name, source, hash_steps(parts, out))


_PAIRS = """b AS (SELECT DISTINCT l_orderkey AS k, {item} AS i FROM lineitem),
e AS (SELECT x.i AS src, y.i AS dst, count(*) AS mult FROM b x JOIN b y ON x.k = y.k AND x.i < y.i GROUP BY ALL)"""
_CANON = """e AS (SELECT least(a, b) AS src, greatest(a, b) AS dst, count(*) AS mult FROM raw WHERE a IS NOT NULL AND b IS NOT NULL AND a <> b GROUP BY ALL)"""
_CODE = "CAST('0x' || substr(md5({0}), 1, 15) AS BIGINT)"

EDGES = {
    "copurchase": _PAIRS.format(item="l_partkey"),
    "supp_supp": _PAIRS.format(item="l_suppkey"),
    "cust_part": "raw AS (SELECT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey),\n" + _CANON,
    "cust_supp": "raw AS (SELECT 2 * o_custkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey),\n" + _CANON,
    "part_supp": "raw AS (SELECT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem),\n" + _CANON,
    "user_key": "raw AS (SELECT 2 * user_id AS a, 2 * CAST(json_extract(props, '$.k') AS BIGINT) + 1 AS b FROM events),\n" + _CANON,
    "geo_forest": "raw AS (SELECT 4 * c_custkey AS a, 4 * CAST(c_nationkey AS BIGINT) + 1 AS b FROM customer UNION ALL "
    "SELECT 4 * CAST(n_nationkey AS BIGINT) + 1, 4 * CAST(n_regionkey AS BIGINT) + 2 FROM nation),\n" + _CANON,
    "page_link": "lk AS (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages),\n"
    f"raw AS (SELECT 2 * page_id AS a, 2 * {_CODE.format('t')} + 1 AS b FROM lk),\n" + _CANON,
    "doc_line": "ln AS (SELECT DISTINCT doc_id, trim(x, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE trim(x, ' ') <> ''),\n"
    "sh AS (SELECT line FROM ln GROUP BY line HAVING count(*) > 1),\n"
    f"raw AS (SELECT 2 * doc_id AS a, 2 * {_CODE.format('line')} + 1 AS b FROM ln JOIN sh USING (line)),\n" + _CANON,
    "toy": "e AS (SELECT a.range AS src, b.range AS dst, 1 AS mult FROM range(1, 6) a, range(1, 6) b WHERE a.range < b.range)",
}


def graph(name: str, thr: str = "21474836") -> str:
    """CTEs g(src, dst, mult, h, thr), v(id)."""
    return (
        EDGES[name] + ",\n" + hash_ctes("hz", "e", ["src", "dst"]) + ",\n"
        f"g AS MATERIALIZED (SELECT src, dst, mult, h, CAST({thr} AS BIGINT) AS thr FROM hz),\n"
        "v AS MATERIALIZED (SELECT src AS id FROM g UNION SELECT dst FROM g)"
    )


def sims(runs: int, seed: int = 7) -> str:
    return f"s0 AS (SELECT range AS sim FROM range({runs})),\n" + hash_ctes("s1", "s0", [str(seed), "sim"], "x") + ",\nsims AS MATERIALIZED (SELECT sim, x FROM s1)"


def sampled(runs: int, sampler: str = "xor", seed: int = 7, op: str = "<=") -> str:
    if sampler == "xor":
        return sims(runs, seed) + f",\nsampled AS MATERIALIZED (SELECT sim, src, dst FROM g, sims WHERE xor(h, x) {op} thr)"
    if sampler == "remix":
        return (
            sims(runs, seed) + ",\nhx AS (SELECT * FROM g, sims),\n" + hash_ctes("hd", "hx", ["h", "x"], "d")
            + f",\nsampled AS MATERIALIZED (SELECT sim, src, dst FROM hd WHERE d {op} thr)"
        )
    return (
        f"si AS (SELECT range AS sim FROM range({runs})),\nhx AS (SELECT * FROM g, si),\n" + hash_ctes("hd", "hx", ["src", "dst", "sim", str(seed)], "d")
        + f",\nsampled AS MATERIALIZED (SELECT sim, src, dst FROM hd WHERE d {op} thr)"
    )


MEMO = """arcs AS MATERIALIZED (SELECT sim, src AS u, dst AS v FROM sampled UNION ALL SELECT sim, dst, src FROM sampled),
lab(sim, id, label) USING KEY (sim, id) AS (
  SELECT DISTINCT sim, u, u FROM arcs
  UNION
  SELECT a.sim, a.v, min(l.label) FROM lab l JOIN arcs a ON a.sim = l.sim AND a.u = l.id
  JOIN recurring.lab c ON c.sim = a.sim AND c.id = a.v WHERE l.label < c.label GROUP BY a.sim, a.v),
memo AS MATERIALIZED (SELECT sim, id, label FROM lab),
sizes AS MATERIALIZED (SELECT sim, label, count(*) AS size FROM memo GROUP BY sim, label),
ms AS MATERIALIZED (SELECT sim, id, label, size FROM memo JOIN sizes USING (sim, label))"""


def gains(runs: int, covered: str = "", seeds: str = "") -> str:
    """A SELECT of (id, gain_sum) of vertices that are not seeds, given covered (sim, label)."""
    open_rows = f"WHERE NOT EXISTS (SELECT 1 FROM {covered} c WHERE c.sim = ms.sim AND c.label = ms.label)" if covered else ""
    rest = f"WHERE v.id NOT IN (SELECT id FROM {seeds})" if seeds else ""
    return f"""SELECT v.id, CAST(coalesce(f.s, 0) + {runs} - coalesce(t.n, 0) AS BIGINT) AS gain_sum
FROM v LEFT JOIN (SELECT id, count(*) AS n FROM ms GROUP BY id) t ON t.id = v.id
LEFT JOIN (SELECT id, sum(size) AS s FROM ms {open_rows} GROUP BY id) f ON f.id = v.id {rest}"""


def chosen(runs: int, k: int) -> str:
    """CTEs seeds1 .. seedsk(rank, id, gain_sum): the greedy choice, unrolled."""
    text = []
    for i in range(1, k + 1):
        if i == 1:
            text.append(f"g1 AS MATERIALIZED ({gains(runs)})")
            text.append("seeds1 AS MATERIALIZED (SELECT 1 AS rank, id, gain_sum FROM g1 ORDER BY gain_sum DESC, id LIMIT 1)")
        else:
            b = i - 1
            text.append(f"cov{b} AS MATERIALIZED (SELECT DISTINCT sim, label FROM ms WHERE id IN (SELECT id FROM seeds{b}))")
            text.append(f"g{i} AS MATERIALIZED ({gains(runs, f'cov{b}', f'seeds{b}')})")
            text.append(
                f"seeds{i} AS MATERIALIZED (SELECT * FROM seeds{b} UNION ALL (SELECT {i}, id, gain_sum FROM g{i} ORDER BY gain_sum DESC, id LIMIT 1))"
            )
    return ",\n".join(text)


def with_(*parts: str, select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + select


def seeds_sql(graph_name: str, runs: int, k: int, thr: str = "21474836", sampler: str = "xor") -> str:
    return with_(
        graph(graph_name, thr), sampled(runs, sampler), MEMO, chosen(runs, k),
        select=f"SELECT CAST(rank AS INT) AS rank, id, gain_sum, CAST(sum(gain_sum) OVER (ORDER BY rank) AS BIGINT) AS sigma_sum FROM seeds{k}",
    )


def reach(arcs: str, starts: str, keys: str = "sim") -> str:
    """CTE r(keys, id, round): breadth-first over (keys, u, v) arcs."""
    same = " AND ".join(f"a.{k.strip()} = r.{k.strip()}" for k in keys.split(","))
    seen = " AND ".join(f"q.{k.strip()} = a.{k.strip()}" for k in keys.split(","))
    listed = ", ".join(f"a.{k.strip()}" for k in keys.split(","))
    return f"""r({keys}, id, round) USING KEY ({keys}, id) AS (
  SELECT {keys}, id, 0 FROM {starts}
  UNION
  SELECT {listed}, a.v, min(r.round) + 1 FROM r JOIN {arcs} a ON {same} AND a.u = r.id
  WHERE NOT EXISTS (SELECT 1 FROM recurring.r q WHERE {seen} AND q.id = a.v) GROUP BY {listed}, a.v)"""


BOTH = "arcs AS MATERIALIZED (SELECT sim, src AS u, dst AS v FROM sampled UNION ALL SELECT sim, dst, src FROM sampled)"
ARCS = "ar AS (SELECT src AS u, dst AS v FROM e UNION ALL SELECT dst, src FROM e)"
DEG = ARCS + ",\ndg AS MATERIALIZED (SELECT u AS id, count(*) AS d FROM ar GROUP BY u)"
