"""Connected components of an edge table by contraction, without propagation rounds
that grow with the diameter.

Each round hooks every vertex onto its smallest neighbour, flattens the hooks by
pointer jumping and replaces the edges by the edges between roots. All labels are
the smallest id of the component, so the result does not depend on the order of
tasks or retries.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spreadmax.session import release, written


def _flatten(parent: DataFrame, by: list[str], keep) -> DataFrame:
    """Pointer jumping until every vertex points at a root; `parent` is a table of its own, which goes."""
    parent_table = parent
    while True:
        above = parent.select(*by, F.col("id").alias("root"), F.col("root").alias("upper"))
        jumped = parent.join(above, [*by, "root"], "left").select(
            *by, "id", F.coalesce("upper", "root").alias("root"), (F.col("upper") < F.col("root")).alias("moved")
        )
        after = keep(jumped)
        release(parent_table)
        jumped = parent_table = after
        if not jumped.filter("moved").limit(1).count():
            return jumped.select(*by, "id", "root")
        parent = jumped.select(*by, "id", "root")


def contracted_components(edges: DataFrame, by: list[str] | None = None, keep=None) -> DataFrame:
    """(by..., src, dst) -> (by..., id, label): label is the smallest id reachable.

    `by` columns split the input into graphs of their own (simulations). Vertices
    without an edge are absent: they are components by themselves. Self-loops and
    repeated edges are harmless; rows with a null end are ignored. `keep`
    materialises a table (default: a written table in the shared folder).
    """
    by = by or []
    keep = keep or (lambda df: written(df, "contract"))
    live = keep(
        edges.filter(F.col("src").isNotNull() & F.col("dst").isNotNull()).select(
            *by, F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")
        )
    )
    loops = live.filter("src = dst").select(*by, F.col("src").alias("id"), F.col("src").alias("root")).distinct()
    live = live.filter("src < dst")
    labels = None
    while live.limit(1).count():
        ends = live.select(*by, F.col("dst").alias("id"), F.col("src").alias("root")).unionByName(
            live.select(*by, F.col("src").alias("id"), F.col("src").alias("root"))
        )
        roots = _flatten(keep(ends.groupBy(*by, "id").agg(F.min("root").alias("root"))), by, keep)
        if labels is None:
            labels = roots
        else:
            onto = roots.select(*by, F.col("id").alias("root"), F.col("root").alias("upper"))
            labels = keep(
                labels.join(onto, [*by, "root"], "left").select(*by, "id", F.coalesce("upper", "root").alias("root"))
            )
        low = roots.select(*by, F.col("id").alias("src"), F.col("root").alias("low"))
        high = roots.select(*by, F.col("id").alias("dst"), F.col("root").alias("high"))
        live = keep(
            live.join(low, [*by, "src"])
            .join(high, [*by, "dst"])
            .filter("low <> high")
            .select(*by, F.least("low", "high").alias("src"), F.greatest("low", "high").alias("dst"))
            .distinct()
        )
    if labels is None:
        return loops.withColumnRenamed("root", "label")
    alone = loops.join(labels.select(*by, "id"), [*by, "id"], "left_anti")
    return labels.unionByName(alone).withColumnRenamed("root", "label")
