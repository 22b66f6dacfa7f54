"""Mesh exchange files and point tables in other formats; block-wise and curve-sorted sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.operators import ranks


def numbered_lines(spark: SparkSession, path: str) -> DataFrame:
    """(line, text) of a text file, 0-based: file order is kept per partition, partitions are numbered in order."""
    lines = spark.read.text(path).withColumn("_pos", F.monotonically_increasing_id())
    return ranks.running(lines, ["_pos"]).select(F.col("rank").alias("line"), F.col("value").alias("text"))


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """Line i after the header (vertex and edge counts) lists the neighbours of vertex i, from 1; '%' lines are comments."""
    lines = ranks.running(spark.read.text(path).where("value not like '\\%%'").withColumn("_pos", F.monotonically_increasing_id()), ["_pos"])
    body = lines.where("rank > 0").select((F.col("rank") - 1).alias("src"), F.explode(F.split(F.trim("value"), r"\s+")).alias("n")).where("n <> ''")
    arcs = body.select("src", (F.col("n").cast("long") - 1).alias("dst"))
    return arcs.where("src < dst").select("src", "dst", F.lit(1.0).alias("ew")).distinct()


def read_coords(spark: SparkSession, path: str, dims=("x", "y")) -> DataFrame:
    """Line i holds the coordinates of vertex i."""
    cells = numbered_lines(spark, path).select(F.col("line").alias("pid"), F.split(F.trim("text"), r"\s+").alias("c"))
    return cells.select("pid", *(F.get("c", F.lit(n)).cast("double").alias(d) for n, d in enumerate(dims)), F.lit(1.0).alias("w"))


def read_points(spark: SparkSession, path: str, fmt: str, dims=("x", "y")) -> tuple[DataFrame, DataFrame]:
    """(points, rejects) of CSV, JSON or ORC files with declared columns pid, dims and w; unreadable rows are rejects."""
    schema = "pid long, " + ", ".join(f"{d} double" for d in dims) + ", w double"
    if fmt == "orc":
        df = spark.read.schema(schema).orc(path).withColumn("_corrupt", F.lit(None).cast("string"))
    else:
        reader = spark.read.schema(schema + ", _corrupt string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt")
        df = (reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path)).persist()
    return df.where("_corrupt is null").drop("_corrupt"), df.where("_corrupt is not null")


def write_blocks(assignment: DataFrame, points: DataFrame, path: str, directories: bool = True) -> None:
    """One location a block: a directory each, or (for very many blocks) files by ranges of blocks."""
    rows = points.join(assignment.select("pid", "block"), "pid")
    if directories:
        rows.repartition("block").write.mode("overwrite").partitionBy("block").parquet(path)
    else:
        rows.repartitionByRange("block").sortWithinPartitions("block").write.mode("overwrite").parquet(path)


def write_sorted(points: DataFrame, path: str, dims=("x", "y")) -> None:
    """Curve-sorted files, whose row groups have tight bounds on the coordinates and the key."""
    ranks.spatial_sort(points, list(dims)).write.mode("overwrite").parquet(path)
