"""Component sizes, initial gains and marginal gains from the memo.

gain_sum of a vertex is the sum of its component sizes over the simulations
that are not covered; a vertex that a simulation leaves alone counts 1 there.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spreadmax.operators.components import components
from spreadmax.operators.graph import CascadeGraph
from spreadmax.session import release, written

#: Components of more vertices than this are heavy: their labels are broadcast to the memo instead of shuffled.
HEAVY_ROWS = 100_000
#: Labels that are broadcast at most. With more heavy ones, the bound on size rises until so few are left.
HEAVY_LABELS = 100_000
#: Simulations of one partition of a saved memo.
SIM_RANGE = 256


def component_sizes(memo: DataFrame) -> DataFrame:
    return memo.groupBy("sim", "label").agg(F.count(F.lit(1)).alias("size"))


def sized(memo: DataFrame, sizes: DataFrame, heavy_rows: int = HEAVY_ROWS, heavy_labels: int = HEAVY_LABELS) -> DataFrame:
    """memo with size. Rows of giant components would meet in one task: their labels, whose number is bounded, are broadcast."""
    found = sizes.filter(F.col("size") > heavy_rows).agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("rows")).head()
    if not found["n"]:
        return memo.join(sizes, ["sim", "label"])
    # components above rows / heavy_labels are fewer than heavy_labels
    bound = heavy_rows if found["n"] <= heavy_labels else max(heavy_rows, found["rows"] // heavy_labels)
    near = F.broadcast(sizes.filter(F.col("size") > bound).select("sim", "label", F.col("size").alias("giant")))
    known = memo.join(near, ["sim", "label"], "left")
    large = known.filter("giant IS NOT NULL").withColumnRenamed("giant", "size")
    rest = known.filter("giant IS NULL").drop("giant").join(sizes.filter(F.col("size") <= bound), ["sim", "label"])
    return large.unionByName(rest)


def gains_of(vertices: DataFrame, memo_sized: DataFrame, runs: int) -> DataFrame:
    """(id, gain_sum, gain) of every vertex from rows that carry their size: one aggregate, one join."""
    own = memo_sized.groupBy("id").agg(F.sum("size").alias("s"), F.count(F.lit(1)).alias("n"))
    total = F.coalesce(F.col("s"), F.lit(0)) + runs - F.coalesce(F.col("n"), F.lit(0))
    return vertices.join(own, "id", "left").select("id", total.cast("long").alias("gain_sum"), (total / runs).alias("gain"))


def initial_gains(vertices: DataFrame, memo: DataFrame, sizes: DataFrame, runs: int) -> DataFrame:
    """(id, gain_sum, gain) of every vertex."""
    return gains_of(vertices, sized(memo, sizes), runs)


def covered_by(memo: DataFrame, seeds: DataFrame) -> DataFrame:
    """(sim, label) of components that hold a seed: at most seeds x simulations rows."""
    return memo.join(F.broadcast(seeds.select("id")), "id", "left_semi").select("sim", "label").distinct()


def marginal_gains(vertices: DataFrame, memo_sized: DataFrame, covered: DataFrame, seeds: DataFrame, runs: int) -> DataFrame:
    """(id, gain_sum) of every vertex that is not a seed, given what the seeds cover: one aggregate over the memo."""
    taken = F.broadcast(covered.withColumn("taken", F.lit(True)))
    counted = F.sum(F.when(F.col("taken").isNull(), F.col("size")))
    own = memo_sized.join(taken, ["sim", "label"], "left").groupBy("id").agg(counted.alias("s"), F.count(F.lit(1)).alias("n"))
    rest = vertices.join(F.broadcast(seeds.select("id")), "id", "left_anti")
    return rest.join(own, "id", "left").select(
        "id", (F.coalesce("s", F.lit(0)) + runs - F.coalesce("n", F.lit(0))).cast("long").alias("gain_sum")
    )


@dataclass
class Memo:
    """Labels and sizes of R simulations of a graph, ready for selection; can be saved and opened again."""

    vertices: DataFrame
    rows: DataFrame  # sim, id, label, size
    runs: int

    @classmethod
    def build(cls, g: CascadeGraph, runs: int, strategy: str = "auto", seed: int = 7, sampler: str = "xor", width: int = 8) -> Memo:
        memo = written(components(g, runs, strategy, seed, sampler, width), "memo")
        rows = written(sized(memo, component_sizes(memo)), "memo")
        release(memo)
        return cls(written(g.vertices, "vertices"), rows, runs)

    @classmethod
    def of(cls, vertices: DataFrame, memo: DataFrame, runs: int) -> Memo:
        return cls(vertices, written(sized(memo, component_sizes(memo)), "memo"), runs)

    def gains(self) -> DataFrame:
        return gains_of(self.vertices, self.rows, self.runs)

    def release(self) -> None:
        """Delete its tables; only when nothing reads it any more."""
        release(self.rows)
        release(self.vertices)

    def sizes(self) -> DataFrame:
        return self.rows.select("sim", "label", "size").distinct()

    def save(self, path: str) -> None:
        """Rows in partitions of SIM_RANGE simulations, by id within a file, so that readers of some simulations or
        some vertices skip the rest; the number of simulations beside them."""
        spark = self.rows.sparkSession
        part = F.floor(F.col("sim") / SIM_RANGE).cast("int")
        self.rows.withColumn("sims", part).sortWithinPartitions("sims", "id").write.partitionBy("sims").parquet(f"{path}/rows")
        self.vertices.write.parquet(f"{path}/vertices")
        spark.createDataFrame([(self.runs,)], "runs int").coalesce(1).write.parquet(f"{path}/runs")

    @classmethod
    def load(cls, spark, path: str) -> Memo:
        runs = spark.read.parquet(f"{path}/runs").head()["runs"]
        rows = spark.read.schema("sim int, id long, label long, size long, sims int").parquet(f"{path}/rows").drop("sims")
        return cls(spark.read.parquet(f"{path}/vertices"), rows, runs)


def size_histogram(sizes: DataFrame) -> DataFrame:
    return sizes.groupBy("size").agg(F.count(F.lit(1)).alias("components"))


def giant_share(sizes: DataFrame, n: int) -> DataFrame:
    """Per simulation the largest component's share of all vertices."""
    return sizes.groupBy("sim").agg(F.max("size").alias("largest")).withColumn("share", F.round(F.col("largest") / n, 6))


def giant_labels(sizes: DataFrame) -> DataFrame:
    """(sim, label, size): the largest component of each simulation, of equal ones that of the smaller label."""
    return sizes.groupBy("sim").agg(F.max_by("label", F.struct("size", -F.col("label"))).alias("label"), F.max("size").alias("size"))


def running_sigma(seeds: DataFrame) -> DataFrame:
    """(rank, id, gain_sum) with sigma_sum, the running total."""
    upto = Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)  # K rows
    return seeds.withColumn("sigma_sum", F.sum("gain_sum").over(upto))
