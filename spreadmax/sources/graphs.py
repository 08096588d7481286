"""Graphs derived from the given tables: (src, dst, mult) with src < dst, one row per edge.

Bipartite graphs code their sides into the ids (2 * key + side), so builders
need no dictionary; page links and shared lines number their strings by hash.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadmax.operators.graph import canonicalise


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table, pruned to the named columns."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


#: Items of a basket that are paired in one task; larger baskets are dealt to blocks.
BASKET = 512
#: Parts of a line that many documents have.
LINE_PARTS = 64


def _co_occurring(df: DataFrame, key: str, item: str, basket: int = BASKET) -> DataFrame:
    """Pairs of items that share a key; mult counts the keys.

    A basket of more than `basket` items is dealt to blocks, and each pair of its blocks is a join key of its own.
    Its edges are all its pairs: that is the graph asked for, so their number grows with the square of the basket.
    """
    items = df.select(key, F.col(item).alias("src")).filter(F.col(key).isNotNull() & F.col("src").isNotNull()).distinct()
    large = items.groupBy(key).agg(F.ceil(F.count(F.lit(1)) / basket).cast("int").alias("blocks")).filter("blocks > 1")
    dealt = items.join(large, key, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    dealt = dealt.withColumn("block", F.pmod(F.xxhash64("src"), "blocks").cast("int"))
    a = dealt.select(key, F.col("block").alias("low"), F.explode(F.sequence("block", F.col("blocks") - 1)).alias("high"), "src")
    b = dealt.select(key, F.explode(F.sequence(F.lit(0), "block")).alias("low"), F.col("block").alias("high"), F.col("src").alias("dst"))
    return canonicalise(a.join(b, [key, "low", "high"]).filter("low < high OR src < dst"))


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _co_occurring(load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey"), "l_orderkey", "l_partkey")


def supp_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _co_occurring(load(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey"), "l_orderkey", "l_suppkey")


def _traded(spark: SparkSession, sf_dir: str, right: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", right)
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    return canonicalise(
        lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
            (2 * F.col("o_custkey")).alias("src"), (2 * F.col(right) + 1).alias("dst")
        )
    )


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _traded(spark, sf_dir, "l_partkey")


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _traded(spark, sf_dir, "l_suppkey")


def part_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey")
    return canonicalise(lines.select((2 * F.col("l_partkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst")))


def interactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, ts) of events: user to the key in the event's JSON."""
    key = F.get_json_object("props", "$.k").cast("long")
    return load(spark, sf_dir, "events", "user_id", "props", "ts").select(
        (2 * F.col("user_id")).alias("src"), (2 * key + 1).alias("dst"), F.col("ts").cast("timestamp").alias("ts")
    )


def user_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    return canonicalise(interactions(spark, sf_dir))


def geo_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer - nation - region: a forest (4 * key + level)."""
    low = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey").select(
        (4 * F.col("c_custkey")).alias("src"), (4 * F.col("c_nationkey").cast("long") + 1).alias("dst")
    )
    high = load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").select(
        (4 * F.col("n_nationkey").cast("long") + 1).alias("src"), (4 * F.col("n_regionkey").cast("long") + 2).alias("dst")
    )
    return canonicalise(low.unionByName(high))


#: How far a product in single precision may lie from the cosine; pairs above `least` less this are computed again in full.
SLACK = 1e-4
#: Rows of a block that are multiplied at once.
STRIP = 512


def _similar(least: float):
    """The kernel of `embed_sim`: vectors of two blocks -> (ia, ib, cosine) of pairs that may be above `least`."""

    def ordered(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Dot products of rows, summed from the first dimension to the last."""
        out = np.zeros(len(x))
        for j in range(x.shape[1]):
            out += x[:, j] * y[:, j]
        return out

    def solve(rows: pa.Table) -> pa.Table:
        ids, block = (rows.column(c).to_numpy() for c in ("vec_id", "block"))
        low, high = rows.column("low")[0].as_py(), rows.column("high")[0].as_py()
        lists = rows.column("embedding").combine_chunks()
        dims = pc.list_value_length(lists).to_numpy(zero_copy_only=False)
        found = []
        for dim in np.unique(dims):
            own = np.flatnonzero(dims == dim)
            x = lists.take(pa.array(own)).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(own), dim)
            size = np.sqrt(ordered(x, x))
            own, x, size = (z[size > 0] for z in (own, x, size))  # without a length there is no cosine
            unit = (x / size[:, None]).astype(np.float32)
            first, second = np.flatnonzero(block[own] == low), np.flatnonzero(block[own] == high)
            for at in range(0, len(first), STRIP):
                strip = first[at : at + STRIP]
                i, j = np.nonzero(unit[strip] @ unit[second].T > least - SLACK)
                i, j = strip[i], second[j]
                if low == high:
                    once = ids[own[i]] < ids[own[j]]
                    i, j = i[once], j[once]
                found.append((ids[own[i]], ids[own[j]], ordered(x[i], x[j]) / (size[i] * size[j])))
        none = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table(dict(zip(("ia", "ib", "cosine"), (np.concatenate(c) for c in zip(none, *found)), strict=True)))

    return solve


def embed_sim(spark: SparkSession, sf_dir: str, least: float = 0.3, block_rows: int = 4096) -> DataFrame:
    """Pairs of vectors with a cosine above `least`, with w = cosine scaled from `least` .. 1 into 0 .. 1.

    A stated comparison of all vectors with all, by pairs of blocks: every vector goes to each block pair that its
    block belongs to, so a task holds `2 * block_rows` vectors on average and nothing is broadcast. A task multiplies
    its blocks as matrices in single precision and computes the pairs near or above `least` again in double precision.
    """
    v = load(spark, sf_dir, "embeddings", "vec_id", "embedding").withColumn("vec_id", F.col("vec_id").cast("long"))
    v = v.filter(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & ~F.exists("embedding", lambda x: x.isNull()))
    blocks = max(1, -(-v.count() // block_rows))
    dealt = v.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    other = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    pairs = other.select(F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "vec_id", "embedding")
    found = pairs.groupBy("low", "high").applyInArrow(_similar(least), "ia long, ib long, cosine double")
    rounded = found.withColumn("cosine", F.round("cosine", 6))
    return rounded.filter(F.col("cosine") > least).select(
        F.least("ia", "ib").alias("src"), F.greatest("ia", "ib").alias("dst"), F.lit(1).cast("long").alias("mult"),
        F.round((F.col("cosine") - least) / (1 - least), 6).alias("w"),
    )


def string_id(text: str):
    """A 60-bit number for a string, from md5: dictionary coding without a global numbering. Of 1e8 different
    strings two meet with a chance of 0.4 %."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the targets of their links; directed links are made undirected."""
    links = load(spark, sf_dir, "pages", "page_id", "html").select(
        "page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target")
    )
    return canonicalise(links.select((2 * F.col("page_id")).alias("src"), (2 * string_id("target") + 1).alias("dst")))


def doc_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and the trimmed lines that at least two of them have.

    Lines are known by their number from the scan on, so no text is shuffled; a line that many documents have is
    counted and joined in LINE_PARTS parts, by document.
    """
    lines = (
        load(spark, sf_dir, "documents", "doc_id", "text")
        .select("doc_id", F.explode(F.split("text", "\n")).alias("raw"))
        .select("doc_id", F.trim("raw").alias("raw"))
        .filter("raw <> ''")
        .select("doc_id", string_id("raw").alias("line"), F.pmod(F.xxhash64("doc_id"), F.lit(LINE_PARTS)).cast("int").alias("part"))
        .distinct()
    )
    parts = lines.groupBy("line", "part").agg(F.count(F.lit(1)).alias("n"))
    every = Window.partitionBy("line")  # LINE_PARTS rows at most
    shared = parts.withColumn("docs", F.sum("n").over(every)).filter("docs > 1").select("line", "part")
    return canonicalise(
        lines.join(shared, ["line", "part"]).select((2 * F.col("doc_id")).alias("src"), (2 * F.col("line") + 1).alias("dst"))
    )


def toy_samples(spark: SparkSession) -> DataFrame:
    """The worked example: (sim, src, dst) of two samples over the vertices 1 .. 5."""
    rows = [(0, 1, 3), (0, 3, 4), (0, 3, 5), (1, 1, 3), (1, 2, 3), (1, 3, 4), (1, 3, 5)]
    values = ", ".join(f"({s}, {a}L, {b}L)" for s, a, b in rows)
    return spark.sql(f"SELECT * FROM VALUES {values} AS t(sim, src, dst)")


def cycle_of_friends(spark: SparkSession) -> DataFrame:
    """Five vertices and their ten edges: the complete toy graph."""
    values = ", ".join(f"({a}L, {b}L, 1L)" for a in range(1, 6) for b in range(a + 1, 6))
    return spark.sql(f"SELECT * FROM VALUES {values} AS t(src, dst, mult)")


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "copurchase": copurchase, "cust_part": cust_part, "part_supp": part_supp, "cust_supp": cust_supp, "user_key": user_key,
    "geo_forest": geo_forest, "supp_supp": supp_supp, "page_link": page_link, "doc_line": doc_line,
}


def graph_between(spark: SparkSession, sf_dir: str, begin: str, end: str) -> DataFrame:
    """Customer-part edges of orders in a range of dates; the range reaches the scan."""
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate").filter(
        (F.col("o_orderdate") >= F.lit(begin).cast("timestamp_ntz")) & (F.col("o_orderdate") < F.lit(end).cast("timestamp_ntz"))
    )
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    return canonicalise(
        lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
            (2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_partkey") + 1).alias("dst")
        )
    )


def latest_before(events: DataFrame, span: int = 3600) -> DataFrame:
    """(event_id, user_id, k, ts) with `before`: the user of the latest earlier event of the same key that has a user.

    The events of a key are ordered within spans of `span` seconds, not in one task: a key hands the last user of
    each span on to its next one, so a window over whole keys sees one row per span. Ties of ts go by event_id;
    events without a time come first; events without a key are one group.
    """
    cut = events.withColumn("part", F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / span))
    newest = F.max(F.when(F.col("user_id").isNotNull(), F.struct("ts", "event_id", "user_id")))
    ends = cut.groupBy("k", "part").agg(newest.alias("newest"))
    parts = Window.partitionBy("k").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    handed = ends.select("k", "part", F.last("newest.user_id", ignorenulls=True).over(parts).alias("user_id")).filter("user_id IS NOT NULL")
    first = handed.withColumn("own", F.lit(False))
    both = cut.withColumn("own", F.lit(True)).unionByName(first, allowMissingColumns=True)
    earlier = Window.partitionBy("k", "part").orderBy("own", "ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn("before", F.last("user_id", ignorenulls=True).over(earlier)).filter("own").drop("own", "part")


def graph_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reply graph: each event's user and the user of the latest earlier event with the same key."""
    replies = latest_before(interactions_with_ids(spark, sf_dir)).filter("before IS NOT NULL")
    return canonicalise(replies.select(F.col("user_id").alias("src"), F.col("before").alias("dst")))


def interactions_with_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events", "event_id", "user_id", "props", "ts").select(
        "event_id", "user_id", F.get_json_object("props", "$.k").cast("long").alias("k"), "ts"
    )
