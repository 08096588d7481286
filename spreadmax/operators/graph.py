"""The graph: canonical edges, weights attached once, both directions for traversal."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spreadmax.functions.hashing import edge_hash, threshold


def canonicalise(pairs: DataFrame) -> DataFrame:
    """(src, dst, ...) -> one row per undirected edge with src < dst and mult, its number of rows.

    Null ends and self-loops go; reversed and repeated rows are one edge.
    """
    return (
        pairs.filter(F.col("src").isNotNull() & F.col("dst").isNotNull() & (F.col("src") != F.col("dst")))
        .select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst"))
        .groupBy("src", "dst")
        .agg(F.count(F.lit(1)).alias("mult"))
    )


def symmetrise(edges: DataFrame) -> DataFrame:
    """Both orientations of every edge: (u, v, and what else the edges carry)."""
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    both = F.explode(
        F.array(F.struct(F.col("src").alias("u"), F.col("dst").alias("v")), F.struct(F.col("dst").alias("u"), F.col("src").alias("v")))
    )
    return edges.select(both.alias("a"), *rest).select("a.u", "a.v", *rest)


def degrees(edges: DataFrame) -> DataFrame:
    return symmetrise(edges.select("src", "dst")).groupBy(F.col("u").alias("id")).agg(F.count(F.lit(1)).alias("deg"))


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def induced_subgraph(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges with both ends among ids (id)."""
    return edges.join(ids.select(F.col("id").alias("src")), "src", "left_semi").join(
        ids.select(F.col("id").alias("dst")), "dst", "left_semi"
    ).select(*edges.columns)


@dataclass
class CascadeGraph:
    """vertices (id); edges (src, dst, mult, w, h, thr): hash and threshold are computed once."""

    vertices: DataFrame
    edges: DataFrame

    @classmethod
    def of(cls, edges: DataFrame, weight: Column | float, vertices: DataFrame | None = None, fn: str = "murmur3") -> CascadeGraph:
        w = weight if isinstance(weight, Column) else F.lit(float(weight))
        full = edges.withColumn("w", w.cast("double")).withColumn("h", edge_hash("src", "dst", fn)).withColumn("thr", threshold("w"))
        found = vertices_of(edges)
        if vertices is not None:
            found = found.unionByName(vertices.select("id")).distinct()
        return cls(found, full)

    @property
    def arcs(self) -> DataFrame:
        return symmetrise(self.edges.select("src", "dst", "w", "h", "thr"))

    def register(self, name: str) -> None:
        """Views name_edges, name_arcs and name_vertices for SQL."""
        for part in ("edges", "arcs", "vertices"):
            getattr(self, part).createOrReplaceTempView(f"{name}_{part}")


def graph_stats(edges: DataFrame, name: str) -> DataFrame:
    """graph, n, m, avg_mult, m_over_n, mean_degree, max_deg."""
    deg = degrees(edges).agg(F.count(F.lit(1)).alias("n"), F.max("deg").alias("max_deg"))
    m = edges.agg(F.count(F.lit(1)).alias("m"), F.avg("mult").alias("am"))
    return deg.crossJoin(m).select(  # one row each
        F.lit(name).alias("graph"), "n", "m", F.round("am", 6).alias("avg_mult"),
        F.round(F.col("m") / F.col("n"), 6).alias("m_over_n"), F.round(2 * F.col("m") / F.col("n"), 6).alias("mean_degree"), "max_deg",
    )
