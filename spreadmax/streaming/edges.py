"""Streams of interactions, and a memo that grows with them.

A fixed edge hash makes membership in a simulation independent of arrival time,
so new edges can only merge components: each micro-batch relabels the labels
that its kept edges join. Deletions need a rebuild of the touched simulations.

Results go to Parquet in a folder that the executors share; a query that is
started again with the same folder goes on where it stopped.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadmax.operators.connectivity import contracted_components
from spreadmax.operators.graph import CascadeGraph, canonicalise
from spreadmax.operators.sampling import fused_sample
from spreadmax.session import release, shared_dir, written

EVENTS = "event_id LONG, ts TIMESTAMP_NTZ, user_id LONG, event_type STRING, value DOUBLE, props STRING"


def edge_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """(src, dst, ts, event_id) from Parquet files of events as they appear."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).option("pathGlobFilter", "events*.parquet").parquet(path)
    key = F.get_json_object("props", "$.k").cast("long")
    return raw.select(
        (2 * F.col("user_id")).alias("src"), (2 * key + 1).alias("dst"), F.col("ts").cast("timestamp").alias("ts"), "event_id"
    )


def dedup_edges(stream: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each edge once within the watermark."""
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["src", "dst"])


def windowed_edges(stream: DataFrame, kind: str = "tumbling", width: str = "1 day", slide: str = "12 hours", watermark: str = "1 hour") -> DataFrame:
    """(start, src, dst, mult): interactions per window; kind: tumbling, sliding or session."""
    late = stream.withWatermark("ts", watermark)
    if kind == "session":
        span = F.session_window("ts", width)
    else:
        span = F.window("ts", width) if kind == "tumbling" else F.window("ts", width, slide)
    return late.groupBy(span.alias("w"), "src", "dst").agg(F.count(F.lit(1)).alias("mult")).select(F.col("w.start").alias("start"), "src", "dst", "mult")


def running_degree(stream: DataFrame) -> DataFrame:
    """(id, interactions): counts per vertex so far."""
    return stream.select(F.explode(F.array("src", "dst")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("interactions"))


def _place(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/spreadmax/stream-{uuid.uuid4().hex}"


def drained(df: DataFrame, place: str | None = None) -> DataFrame:
    """Run a stream over what is there, in append mode into Parquet, and give what it has closed: windows whose end the
    watermark has passed; the others stay in the state for the next run with the same folder."""
    spark = df.sparkSession
    place = place or _place(spark)
    sink = df.writeStream.outputMode("append").format("parquet").option("path", f"{place}/rows").option("checkpointLocation", f"{place}/offsets")
    sink.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{place}/rows")


def latest(df: DataFrame, keys: list[str], place: str | None = None) -> DataFrame:
    """Run an aggregate over what is there in update mode: each batch writes its changed rows in a folder of its number
    (a batch that is run again writes the same), the last row of a key counts."""
    spark = df.sparkSession
    place = place or _place(spark)

    def step(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{place}/rows/part={number}")

    sink = df.writeStream.outputMode("update").foreachBatch(step).option("checkpointLocation", f"{place}/offsets")
    sink.trigger(availableNow=True).start().awaitTermination()
    values = [c for c in df.columns if c not in keys]
    if not _versions(spark, f"{place}/rows", "part="):
        return spark.createDataFrame([], df.schema)
    rows = spark.read.parquet(f"{place}/rows").drop("part")
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*values), "batch").alias("last"))
    return last.select(*keys, *[F.col("last")[c].alias(c) for c in values])


def merge_batch(memo: DataFrame | None, new_edges: DataFrame, weight: float, runs: int, seed: int = 7) -> DataFrame:
    """The memo after further edges (src, dst, mult): labels joined by kept new edges are contracted among themselves."""
    sampled = written(fused_sample(CascadeGraph.of(new_edges, weight), runs, seed), "sampled")
    if memo is None:
        return written(contracted_components(sampled, by=["sim"]), "memo")
    low = memo.select("sim", F.col("id").alias("src"), F.col("label").alias("ls"))
    high = memo.select("sim", F.col("id").alias("dst"), F.col("label").alias("ld"))
    between = (
        sampled.join(low, ["sim", "src"], "left")
        .join(high, ["sim", "dst"], "left")
        .select("sim", F.coalesce("ls", "src").alias("src"), F.coalesce("ld", "dst").alias("dst"))
    )
    relabel = contracted_components(between, by=["sim"]).withColumnRenamed("label", "to")
    old = memo.join(relabel.select("sim", F.col("id").alias("label"), "to"), ["sim", "label"], "left").select(
        "sim", "id", F.coalesce("to", "label").alias("label")
    )
    ends = sampled.select("sim", F.explode(F.array("src", "dst")).alias("id")).distinct().join(memo, ["sim", "id"], "left_anti")
    fresh = ends.join(relabel, ["sim", "id"], "left").select("sim", "id", F.coalesce("to", "id").alias("label"))
    return written(old.unionByName(fresh), "memo")


def _versions(spark: SparkSession, place: str, prefix: str = "") -> list[int]:
    """Numbers of the whole tables in a folder, in order."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(place)
    fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not fs.exists(path):
        return []
    named = [s.getPath() for s in fs.listStatus(path) if s.getPath().getName().startswith(prefix)]
    done = [p.getName()[len(prefix) :] for p in named if fs.exists(jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS"))]
    return sorted(int(n) for n in done if n.isdigit())


MEMO = "sim int, id long, label long"


def stream_memo(spark: SparkSession, path: str, weight: float, runs: int, seed: int = 7, place: str | None = None) -> DataFrame:
    """The memo of all edges of a stream, kept up by foreachBatch.

    Version b of the memo is the table of batch b in `place`, beside the offsets of the
    query: started again with the same `place`, it goes on from its last version, and a
    batch that is run again begins from the version before it. All versions but the last two go.
    """
    place = place or _place(spark)
    memos = f"{place}/memo"
    version = lambda b: spark.read.schema(MEMO).parquet(f"{memos}/{b}")

    def step(batch: DataFrame, number: int) -> None:
        before = [b for b in _versions(spark, memos) if b < number]
        edges = written(canonicalise(batch), "edges")
        if edges.limit(1).count():
            after = merge_batch(version(before[-1]) if before else None, edges, weight, runs, seed)
            after.select("sim", "id", "label").write.mode("overwrite").parquet(f"{memos}/{number}")
            release(after)
            for b in before[:-1]:
                old = version(b)
                old._written_to = f"{memos}/{b}"
                release(old)
        release(edges)

    sink = edge_stream(spark, path).writeStream.foreachBatch(step).option("checkpointLocation", f"{place}/offsets")
    sink.trigger(availableNow=True).start().awaitTermination()
    done = _versions(spark, memos)
    return version(done[-1]) if done else spark.createDataFrame([], MEMO)
