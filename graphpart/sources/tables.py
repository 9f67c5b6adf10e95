"""Scans, edge files and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
EDGE_SCHEMA = "src long, dst long"


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def read_edges(spark: SparkSession, path: str | None = None, fmt: str = "parquet", table: str | None = None, **options) -> DataFrame:
    """Edges (src, dst) from parquet, csv, tsv, json, orc, text (two ids a line) or a catalog table."""
    if table:
        return spark.table(table).select("src", "dst")
    if fmt in ("csv", "tsv"):
        return spark.read.options(**{"sep": "\t" if fmt == "tsv" else ",", "comment": "#"} | options).schema(EDGE_SCHEMA).csv(path)
    if fmt == "json":
        return spark.read.schema(EDGE_SCHEMA).json(path)
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).where("value NOT LIKE '#%' AND trim(value) <> ''").select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    return spark.read.format(fmt).load(path).select("src", "dst")


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """Edges from lines 'v: u1 u2 ...' or 'v u1 u2 ...'."""
    parts = F.split(F.trim(F.regexp_replace("value", "[:,\t]", " ")), " +")
    return spark.read.text(path).where("trim(value) <> '' AND value NOT LIKE '#%'").select(parts[0].cast("long").alias("src"), F.explode(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0)))).cast("long").alias("dst"))


def write_adjacency(arcs: DataFrame, path: str) -> None:
    """One line a vertex; for vertices whose lists fit a row."""
    arcs.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("to")).select(F.concat_ws(" ", F.col("src").cast("string"), F.transform("to", lambda x: x.cast("string")))).write.mode("overwrite").text(path)


def write_labels(labels: DataFrame, path: str, fmt: str = "parquet") -> None:
    labels.select("v", "label").write.mode("overwrite").format(fmt).save(path)


def write_placed(placed: DataFrame, path: str) -> None:
    """A directory for each label, so that readers of a label prune the others."""
    placed.write.mode("overwrite").partitionBy("label").parquet(path)


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by key: joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def save_state(labels: DataFrame, path: str, manifest: dict) -> None:
    """Labels and a manifest (k, c, seed, t, label_set) to restart from."""
    import json

    labels.select("v", "label").write.mode("overwrite").parquet(f"{path}/labels")
    spark = labels.sparkSession
    spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load_state(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    import json

    return spark.read.parquet(f"{path}/labels"), json.loads(spark.read.text(f"{path}/manifest").first()[0])
