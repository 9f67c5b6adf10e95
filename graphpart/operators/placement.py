"""Placement by label: rows of one label in one partition, and composite ids."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def place(df: DataFrame, labels: DataFrame, k: int, key: str = "v") -> DataFrame:
    """df with its vertex's label and the composite id pid (v, label); partition number = label."""
    rows = df.join(labels.select(F.col("v").alias(key), "label"), key)
    return rows.withColumn("pid", F.struct(F.col(key).alias("v"), "label")).repartitionById(k, F.col("label"))


def placed_layout(placed: DataFrame) -> DataFrame:
    """(part, labels, rows): what each partition holds."""
    return placed.groupBy(F.spark_partition_id().alias("part")).agg(F.count_distinct("label").alias("labels"), F.count(F.lit(1)).alias("rows"))


def parts_of_labels(placed: DataFrame) -> DataFrame:
    """(label, parts, rows): over how many partitions a label's rows lie (one, if they are placed), and how many rows it has."""
    at = placed.select("label", F.spark_partition_id().alias("part"))
    return at.groupBy("label").agg(F.count_distinct("part").alias("parts"), F.count(F.lit(1)).alias("rows"))
