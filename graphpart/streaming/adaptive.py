"""Structured Streaming around the method: continuous adaptation, event windows, drift."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphpart.operators import adapt, metrics
from graphpart.operators import state as st
from graphpart.operators.engine import FixedIterations
from graphpart.sources.tables import load_state, save_state


def stream_events(spark: SparkSession, folder: str) -> DataFrame:
    """events files of a folder as a stream, ts as timestamp."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    return spark.readStream.schema(schema).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def edge_rate(events: DataFrame, window: str = "1 day", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """Events a tumbling or sliding window and type; late ones beyond the watermark are left out."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return events.withWatermark("ts", watermark).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "1 hour", watermark: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def first_edges(edges: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each (src, dst) once within the watermark."""
    return edges.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["src", "dst"])


def stream_adapt(edge_stream: DataFrame, state_dir: str, k: int, checkpoint: str, iterations: int = 3, directed: bool = True):
    """A query that adapts the stored labelling to every batch of new edges (src, dst); each batch's state stands in its own folder.

    A batch reads the state of the batch before it and writes its own, so a repeated batch gives the same state again.
    """

    def step(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        labels, manifest = load_state(spark, f"{state_dir}/{batch_id}")
        old = spark.read.parquet(f"{state_dir}/{batch_id}/edges")
        new = old.union(batch.select("src", "dst")).distinct()
        r = adapt.adapt_graph(labels, new, k, directed=directed, halting=FixedIterations(iterations), label_set=manifest["label_set"])
        after = f"{state_dir}/{batch_id + 1}"
        save_state(r.labels, after, {"k": k, "t": manifest["t"] + r.iterations, "label_set": r.label_set, "phi": r.history[-1]["phi"], "rho": r.history[-1]["rho"]})
        new.write.mode("overwrite").parquet(f"{after}/edges")

    return edge_stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint)


def start_state(labels: DataFrame, edges: DataFrame, state_dir: str, k: int) -> None:
    """State before the first batch."""
    save_state(labels, f"{state_dir}/0", {"k": k, "t": 0, "label_set": list(range(k))})
    edges.select("src", "dst").write.mode("overwrite").parquet(f"{state_dir}/0/edges")


def quality_monitor(edges: DataFrame, labels: DataFrame, vertices: DataFrame, k: int) -> DataFrame:
    """One row: phi and rho of a labelling, for a batch's report."""
    return metrics.phi(edges, labels).crossJoin(metrics.rho(vertices.join(labels, "v"), k))


def stream_assign(vertices: DataFrame, labels: DataFrame, k: int) -> DataFrame:
    """Labels for the vertices of a batch that have none yet: the least loaded label."""
    return st.init_from(labels, vertices, "least_loaded", k)
