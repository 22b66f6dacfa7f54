"""Curve sort, global ranks and running weights, in one range shuffle and without unpartitioned windows.

Rows are dealt by key ranges and sorted inside partitions; a narrow pass numbers the rows and sums their weights within the
partition, and the partitions' totals (one row each) are added as prefixes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from meshcut.functions.curves import curve_key, quantize
from meshcut.sources.scratch import written


def default_parts(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def spatial_sort(points: DataFrame, dims: list[str], bits: int = 16, parts: int | None = None, tile_bits: int = 12, curve: str = "hilbert") -> DataFrame:
    """points with hkey and tile, dealt by curve ranges and sorted; equal keys are ordered by pid."""
    names = [f"_g{d}" for d in dims]
    keyed = quantize(points, dims, bits, names).withColumn("hkey", curve_key(names, bits, curve)).drop(*names)
    tile = F.call_function("shiftright", F.col("hkey"), F.lit(max(0, bits * len(dims) - tile_bits)))
    parts = parts or default_parts(points)
    return keyed.withColumn("tile", tile).repartitionByRange(parts, "hkey", "pid").sortWithinPartitions("hkey", "pid")


def running(df: DataFrame, order: list[str], weight: str | None = None, parts: int | None = None, rank: str = "rank", total: str = "cum") -> DataFrame:
    """Adds `rank` (0-based, by the order columns, which must be total) and, with a weight, `total`: its sum up to this row."""

    def number(batches):
        part, at, sums = TaskContext.get().partitionId(), 0, 0
        for b in batches:
            n = b.num_rows
            columns = [*b.columns, pa.array(np.full(n, part, np.int32)), pa.array(np.arange(at, at + n, dtype=np.int64))]
            names = [f.name for f in b.schema] + ["_part", "_rank"]
            if weight:
                w = b.column(b.schema.get_field_index(weight)).to_numpy(zero_copy_only=False)
                s = sums + np.cumsum(w)
                sums = s[-1] if n else sums
                columns.append(pa.array(s))
                names.append("_cum")
            at += n
            yield pa.RecordBatch.from_arrays(columns, names=names)

    kind = df.schema[weight].dataType.simpleString() if weight else None
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema) + ", _part int, _rank long" + (f", _cum {kind}" if weight else "")
    dealt = df.repartitionByRange(parts or default_parts(df), *order).sortWithinPartitions(*order)
    local = written(dealt.mapInArrow(number, schema), "ranks")
    ends = local.groupBy("_part").agg(F.count("*").alias("_n"), *([F.max("_cum").alias("_w")] if weight else []))
    # one row a partition
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = ends.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_n0"), *([F.coalesce(F.sum("_w").over(before), F.lit(0)).alias("_w0")] if weight else []))
    out = local.join(F.broadcast(starts), "_part").withColumn(rank, F.col("_rank") + F.col("_n0"))
    if weight:
        out = out.withColumn(total, (F.col("_cum") + F.col("_w0")).cast(kind))
    return out.drop("_part", "_rank", "_cum", "_n0", "_w0")


def global_rank(points: DataFrame, order: list[str] = ("hkey", "pid")) -> DataFrame:
    return running(points, list(order))


def seed_ranks(n: int, k: int) -> list[int]:
    """Middles of k equal runs of n ranks."""
    return [(2 * i + 1) * n // (2 * k) for i in range(k)]


def sfc_seeds(points: DataFrame, k: int, dims: list[str], by: str = "rank") -> DataFrame:
    """(block, coordinates) of the seeds: the points at the middle ranks of k equal runs along the curve, or, by='weight',
    the first points whose running weight passes the middle of k equal shares. points: with hkey."""
    spark = points.sparkSession
    if by == "weight":
        r = running(points, ["hkey", "pid"], "w")
        total = r.agg(F.max("cum")).first()[0]
        marks = spark.createDataFrame([(i, (2 * i + 1) * total // (2 * k)) for i in range(k)], "block int, mark long")
        hit = r.join(F.broadcast(marks), (F.col("mark") >= F.col("cum") - F.col("w")) & (F.col("mark") < F.col("cum")))
        return hit.select("block", *dims)
    r = running(points, ["hkey", "pid"])
    n = r.count()
    marks = spark.createDataFrame(list(enumerate(seed_ranks(n, k))), "block int, rank long")
    return r.join(F.broadcast(marks), "rank").select("block", *dims)


def random_seeds(points: DataFrame, k: int, dims: list[str], seed: int = 0) -> DataFrame:
    """k points with the least hash of (pid, seed)."""
    top = points.orderBy(F.xxhash64("pid", F.lit(seed)), "pid").limit(k)
    return top.select((F.row_number().over(Window.orderBy(F.xxhash64("pid", F.lit(seed)), "pid")) - 1).alias("block"), *dims)
