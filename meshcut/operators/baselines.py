"""The geometric baselines: curve chunks, recursive coordinate and inertial bisection, jagged sections, hash blocks."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshcut.operators import ranks
from meshcut.operators.kmeans import Partition, balanced_kmeans
from meshcut.sources.scratch import written


def _share(w, cum, total, k):
    """Which of k equal shares the middle of a point's weight falls into."""
    return F.least(k - 1, F.floor((cum - w / 2) * k / total)).cast("int")


def curve_chunks(points: DataFrame, k: int, order: list[str] = ("hkey", "pid")) -> DataFrame:
    """k runs of equal weight along the curve (points with hkey)."""
    r = ranks.running(points, list(order), "w")
    total = r.agg(F.max("cum").alias("total"))
    return r.crossJoin(F.broadcast(total)).select("pid", _share(F.col("w"), F.col("cum"), F.col("total"), F.lit(k)).alias("block"))


def _split(points: DataFrame, axis: str, parts: str) -> DataFrame:
    """Adds `section`: each region cut into `parts` (a column) runs of equal weight along the axis (a column)."""
    r = ranks.running(points, ["region", axis, "pid"], "w")
    ends = r.groupBy("region").agg(F.max("cum").alias("_end"), F.sum("w").alias("_all"))
    within = F.col("cum") - (F.col("_end") - F.col("_all"))
    # as many rows as regions
    return r.join(ends, "region").withColumn("section", _share(F.col("w"), within, F.col("_all"), F.col(parts))).drop("rank", "cum", "_end", "_all")


def coordinate_bisection(points: DataFrame, k: int, dims) -> DataFrame:
    """Halves every region across its widest axis at the weighted median, level by level; odd block counts split unevenly."""
    p = points.select("pid", *dims, "w", F.lit(0).alias("region"), F.lit(k).alias("_k"))
    for _ in range(math.ceil(math.log2(k)) if k > 1 else 0):
        box = p.groupBy("region").agg(*(F.max(d) - F.min(d) for d in dims))
        box = box.toDF("region", *(f"_e{c}" for c in range(len(dims))))
        widest = F.lit(len(dims) - 1)
        for c in range(len(dims) - 2, -1, -1):
            widest = F.when(F.col(f"_e{c}") >= F.greatest(*(F.col(f"_e{j}") for j in range(len(dims)))), F.lit(c)).otherwise(widest)
        cut = p.join(box.select("region", widest.alias("_axis")), "region")
        value = F.col(dims[-1])
        for c, d in enumerate(dims[:-1]):
            value = F.when(F.col("_axis") == c, F.col(d)).otherwise(value)
        p = _bisect(cut.withColumn("_value", value.cast("double"))).select("pid", *dims, "w", "region", "_k")
    return p.select("pid", F.col("region").alias("block"))


def _bisect(p: DataFrame) -> DataFrame:
    """Regions of _k blocks are cut along _value in the proportion floor(_k/2) : ceil(_k/2); region ids count blocks."""
    r = ranks.running(p, ["region", "_value", "pid"], "w")
    ends = r.groupBy("region").agg(F.max("cum").alias("_end"), F.sum("w").alias("_all"))
    within = F.col("cum") - (F.col("_end") - F.col("_all"))
    left = F.floor(F.col("_k") / 2).cast("int")
    low = (within - F.col("w") / 2) * F.col("_k") < F.col("_all") * left
    r = r.join(ends, "region").withColumns({"_low": low | (F.col("_k") < 2)})
    moved = r.withColumns({"region": F.when(F.col("_low"), F.col("region")).otherwise(F.col("region") + left), "_k": F.when(F.col("_k") < 2, F.col("_k")).when(F.col("_low"), left).otherwise(F.col("_k") - left)})
    return moved.drop("rank", "cum", "_end", "_all", "_low")


def principal_axis(sxx: float, sxy: float, syy: float) -> tuple[float, float]:
    """Unit vector of largest spread of a symmetric 2 x 2 matrix; the x axis where there is no preference."""
    half = (sxx - syy) / 2
    root = math.sqrt(half * half + sxy * sxy)
    if root == 0:
        return 1.0, 0.0
    vx, vy = (half + root, sxy) if half >= 0 else (sxy, root - half)
    norm = math.hypot(vx, vy)
    vx, vy = vx / norm, vy / norm
    return (-vx, -vy) if vx < 0 or (vx == 0 and vy < 0) else (vx, vy)


def principal_axis_3d(m: list[list[float]]) -> tuple[float, ...]:
    import numpy as np

    v = np.linalg.eigh(np.array(m))[1][:, -1]
    first = next((x for x in v if abs(x) > 1e-12), 1.0)
    return tuple(float(x) for x in (v if first > 0 else -v))


def region_moments(p: DataFrame, dims) -> DataFrame:
    """Weight, weighted sums and products of every region, in one aggregation."""
    w = F.col("w").cast("double")
    aggs = [F.sum(w).alias("m")] + [F.sum(w * F.col(d)).alias(f"m_{d}") for d in dims]
    aggs += [F.sum(w * F.col(a) * F.col(b)).alias(f"m_{a}{b}") for i, a in enumerate(dims) for b in dims[i:]]
    return p.groupBy("region").agg(*aggs)


def inertial_bisection(points: DataFrame, k: int, dims) -> DataFrame:
    """As coordinate_bisection, across the principal axis of each region. Moments of the k regions reach the driver."""
    spark = points.sparkSession
    dims = list(dims)
    p = points.select("pid", *dims, "w", F.lit(0).alias("region"), F.lit(k).alias("_k"))
    for _ in range(math.ceil(math.log2(k)) if k > 1 else 0):
        axes = []
        for r in region_moments(p, dims).collect():
            mean = [r[f"m_{d}"] / r["m"] for d in dims]
            cov = [[r[f"m_{min(a, b)}{max(a, b)}"] / r["m"] - mean[i] * mean[j] for j, b in enumerate(dims)] for i, a in enumerate(dims)]
            v = principal_axis(cov[0][0], cov[0][1], cov[1][1]) if len(dims) == 2 else principal_axis_3d(cov)
            axes.append((r["region"], *v))
        axis = spark.createDataFrame(axes, "region int, " + ", ".join(f"_v{c} double" for c in range(len(dims))))
        value = sum((F.col(d) * F.col(f"_v{c}") for c, d in enumerate(dims)), F.lit(0.0))
        p = _bisect(p.join(F.broadcast(axis), "region").withColumn("_value", F.round(value, 9))).select("pid", *dims, "w", "region", "_k")
        p = written(p, "inertial")
    return p.select("pid", F.col("region").alias("block"))


def jagged_sections(points: DataFrame, parts: tuple[int, ...], dims) -> DataFrame:
    """parts[0] slabs of equal weight across the first axis, each cut on its own into parts[1] across the second, ..."""
    p = points.select("pid", *dims, "w", F.lit(0).alias("region"))
    for d, m in zip(dims, parts):
        p = _split(p.withColumn("_m", F.lit(m)), d, "_m").withColumn("region", F.col("region") * m + F.col("section")).drop("section", "_m")
    return p.select("pid", F.col("region").alias("block"))


def jagged_parts(k: int, d: int) -> tuple[int, ...]:
    """Factors of k, as near k**(1/d) as they come."""
    out = []
    for left in range(d, 1, -1):
        goal = k ** (1 / left)
        m = min((x for x in range(1, k + 1) if k % x == 0), key=lambda x: (abs(x - goal), x))
        out.append(m)
        k //= m
    return (*out, k)


def lloyd(points: DataFrame, k: int, iters: int = 50, **more) -> Partition:
    """Plain k-means: influence stays 1, no balancing."""
    return balanced_kmeans(points, k, max_iter=iters, balance=False, sample_start=None, **more)


def hash_blocks(points: DataFrame, k: int) -> DataFrame:
    """Control: blocks by the remainder of the id."""
    return points.select("pid", F.pmod(F.col("pid"), F.lit(k)).cast("int").alias("block"))
