"""Sessions and the shared working folder.

Nothing here changes settings that are fixed when a session starts: the engine
works with the session it is given.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}


def local_session(cores: int = 4, partitions: int = 8, memory: str = "4g") -> SparkSession:
    """A session for tests and the bench; a cluster brings its own."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("spreadmax")
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: `spark.checkpoint.dir`.

    Where the session names none, a folder in the warehouse; on one machine
    (tests) a temporary folder of this process.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        if spark.sparkContext.master.startswith("local"):
            _OWN[app] = "file://" + tempfile.mkdtemp(prefix="spreadmax-")
        else:
            _OWN[app] = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + f"/spreadmax-{app}"
    return _OWN[app]


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the JVM may be gone when the interpreter ends
        pass


def written(df: DataFrame, tag: str = "t") -> DataFrame:
    """Cut the lineage of `df` through a Parquet table in the shared folder.

    The table survives lost executors; it is deleted by `release`, or when the driver ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/spreadmax/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_remove, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_to = path
    return out


def _drop(spark: SparkSession, name: str) -> None:
    try:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
    except Exception:  # the JVM may be gone when the interpreter ends
        pass


def bucketed(df: DataFrame, by: str, tag: str = "b", buckets: int | None = None) -> DataFrame:
    """Like `written`, dealt to buckets and sorted by a column: joins on it need no shuffle of this side, however often
    they are repeated. A catalogue table over files in the shared folder, with as many buckets as the session has
    shuffle partitions."""
    spark = df.sparkSession
    name = f"spreadmax_{tag}_{uuid.uuid4().hex}"
    path = f"{shared_dir(spark)}/spreadmax/{name}"
    n = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    df.repartition(n, by).write.bucketBy(n, by).sortBy(by).option("path", path).saveAsTable(name)
    atexit.register(_remove, spark, path)
    atexit.register(_drop, spark, name)
    out = spark.table(name)
    out._written_to, out._table = path, name
    return out


def release(df: DataFrame | None) -> None:
    """Delete the files of a table that `written` or `bucketed` gave, once nothing reads them any more (other DataFrames are left alone)."""
    path = getattr(df, "_written_to", None)
    if path is not None:
        if getattr(df, "_table", None):
            _drop(df.sparkSession, df._table)
        _remove(df.sparkSession, path)


def rewritten(before: DataFrame | None, df: DataFrame, tag: str = "t") -> DataFrame:
    """The next version of a table: written, then the version before it goes. Only for tables that nothing else reads."""
    out = written(df, tag)
    release(before)
    return out
