"""Session defaults and lineage cuts."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import DataFrame, SparkSession


def make_session(cores: int | str = "*", shuffle_partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A local session with the settings the engine is tuned for; on a cluster, use the one you are given."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("graphpart")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, which driver and executors share; a temporary one only where none is set and all run in one process."""
    sc = spark.sparkContext
    have = sc._jsc.sc().getCheckpointDir()
    own = spark.conf.get("spark.checkpoint.dir", None)
    if own or have.isDefined():
        return own or have.get()
    if not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return tempfile.mkdtemp(prefix="graphpart-")


def ship(spark: SparkSession) -> None:
    """Make this package importable on every executor (once per context), wherever the driver found it."""
    sc = spark.sparkContext
    if getattr(sc, "_graphpart_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    archive = os.path.join(tempfile.mkdtemp(prefix="graphpart-"), "graphpart_code.zip")
    with zipfile.ZipFile(archive, "w") as z:
        for folder, _, names in os.walk(root):
            for name in sorted(names):
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(root)))
    sc.addPyFile(archive)
    sc._graphpart_shipped = True


def release(df: DataFrame) -> None:
    """Delete the files of a frame made by ``durable`` that nothing reads any more."""
    rdd = df._jdf.queryExecution().logical().rdd()
    path = rdd.getCheckpointFile()
    if path.isDefined():
        jvm = df.sparkSession.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(path.get())
        at.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def durable_as_dealt(df: DataFrame) -> DataFrame:
    """``durable`` for a frame that ends in a repartition: the result knows how it is dealt, so joins on its keys need no exchange of it.

    An adaptive plan forgets its partitioning, so this one job is planned without.
    """
    conf = df.sparkSession.conf
    adaptive = conf.get("spark.sql.adaptive.enabled")
    conf.set("spark.sql.adaptive.enabled", "false")
    try:
        return durable(df.select("*"))
    finally:
        conf.set("spark.sql.adaptive.enabled", adaptive)


def durable(df: DataFrame) -> DataFrame:
    """Cut lineage through the shared folder."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return _bounded(df.checkpoint(eager=True))


def _bounded(df: DataFrame) -> DataFrame:
    """A checkpointed frame whose size is unknown to the planner where the estimate of it doesn't fit a long.

    A checkpoint keeps the estimate of the plan that it cuts, and a join's estimate is the product of its sides'. In a loop of
    joins the number's digits multiply by round, until the driver has neither the time nor the heap to hold it.
    """
    spark, plan = df.sparkSession, df._jdf.queryExecution().logical()
    try:
        if plan.stats().sizeInBytes() < 1 << 63:
            return df
    except ValueError:  # more digits than Python reads
        pass
    jvm = spark.sparkContext._jvm
    none, some = jvm.scala.Option.empty(), jvm.scala.Option.apply
    same = jvm.org.apache.spark.sql.execution.LogicalRDD(plan.output(), plan.rdd(), plan.outputPartitioning(), plan.outputOrdering(), False, none, spark._jsparkSession, none, some(plan.constraints()))
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, same), spark)
