"""Meshes over point sets: undirected edges, stored once with src < dst."""

from __future__ import annotations

import itertools
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from meshcut.sources.points import load
from meshcut.sources.scratch import written


def lattice_edges(p: DataFrame, dims: list[str], weighted: bool = False) -> DataFrame:
    """Each cell with its next neighbour on every axis and on the main diagonal, where both exist: one equi join a direction."""
    d = len(dims)
    ways = [tuple(int(k == a) for k in range(d)) for a in range(d)] + [(1,) * d]
    other = p.select(F.col("pid").alias("dst"), *(F.col(c).alias(f"_{c}") for c in dims), F.col("w").alias("_w"))
    out = []
    for way in ways:
        on = [F.col(c) + s == F.col(f"_{c}") for c, s in zip(dims, way)]
        ew = F.least("w", "_w").cast("double") if weighted else F.lit(1.0)
        out.append(p.join(other, on).select(F.col("pid").alias("src"), "dst", ew.alias("ew")))
    return reduce(DataFrame.unionByName, out)


def radius_edges(p: DataFrame, r: float, dims: list[str] = ("x", "y")) -> DataFrame:
    """All pairs at most r apart: points meet in grid cells of side r, so the join is on equal cells, not on all pairs.

    A pair of two cells meets in one of them only: points are repeated for their own cell and half of the cells around it.
    The points and r are kept beside the edges, for measures that need not make each edge.
    """
    keys = [f"_k{n}" for n in range(len(dims))]
    cell = [F.floor(F.col(c) / r).cast("long").alias(k) for c, k in zip(dims, keys)]
    left = p.select(F.col("pid").alias("a"), *(F.col(c).alias(f"a{n}") for n, c in enumerate(dims)), *cell)
    right = p.select(F.col("pid").alias("b"), *(F.col(c).alias(f"b{n}") for n, c in enumerate(dims)), *cell)
    none = (0,) * len(dims)
    ways = [w for w in itertools.product((-1, 0, 1), repeat=len(dims)) if w >= none]
    places = F.array(*(F.struct(*((F.col(k) + s).alias(k) for k, s in zip(keys, w)), F.lit(w == none).alias("own")) for w in ways))
    right = right.withColumn("_w", F.explode(places)).select("b", *(f"b{n}" for n in range(len(dims))), *(f"_w.{k}" for k in keys), "_w.own")
    apart = reduce(lambda a, b: a + b, [(F.col(f"a{n}") - F.col(f"b{n}")) * (F.col(f"a{n}") - F.col(f"b{n}")) for n in range(len(dims))])
    near = left.join(right, keys).where((apart <= r * r) & F.when(F.col("own"), F.col("a") < F.col("b")).otherwise(F.col("a") != F.col("b")))
    out = near.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), F.lit(1.0).alias("ew"))
    out._geometric = p, r, tuple(dims)
    return out


def knn_edges(points: DataFrame, q: int, block: int = 500) -> DataFrame:
    """The q nearest neighbours (ties: lower pid) of every vector, made symmetric. Brute force, block against block.

    A product of two blocks leaves few candidates for the q nearest of each row; their distances are then summed coordinate by
    coordinate and rounded to nine places, as the definition has it. Vectors that are null are left out.
    """

    def packed(batches):
        for b in batches:
            for at in range(0, b.num_rows, block):
                part = b.slice(at, block)
                ids = part.column(0).to_numpy(zero_copy_only=False).astype("<i8")
                v = np.array(part.column(1).to_pylist(), "<f8")
                if v.ndim != 2:
                    raise ValueError("vectors differ in length")
                yield pa.RecordBatch.from_arrays([pa.array([ids.tobytes()], pa.binary()), pa.array([v.tobytes()], pa.binary())], names=["ids", "v"])

    def nearest(batches):
        key, mine, best = None, None, []
        for batch in batches:
            for k, ids, v, ids2, v2 in zip(*batch.columns):
                k = k.as_py()
                if k != key:
                    if best:
                        yield least(best)
                    key, best = k, []
                    a = np.frombuffer(ids.as_buffer(), "<i8")
                    x = np.frombuffer(v.as_buffer(), "<f8").reshape(len(a), -1)
                    mine = a, x, (x * x).sum(axis=1)
                a, x, xx = mine
                b = np.frombuffer(ids2.as_buffer(), "<i8")
                y = np.frombuffer(v2.as_buffer(), "<f8").reshape(len(b), -1)
                yy = (y * y).sum(axis=1)
                d = xx[:, None] + yy - 2 * (x @ y.T)
                d[a[:, None] == b] = np.inf
                # beyond what rounding to nine places and the product's own error can turn round
                edge = np.partition(d, min(q, len(b)) - 1, axis=1)[:, min(q, len(b)) - 1] + 4e-9 + 1e-12 * (xx + yy.max())
                i, j = np.nonzero((d <= edge[:, None]) & np.isfinite(d))
                s = np.zeros(len(i))
                for c in range(x.shape[1]):
                    t = x[i, c] - y[j, c]
                    s += t * t
                best.append((a[i], b[j], np.floor(s * 1e9 + 0.5)))
                if len(best) > 20:
                    best = [cut(best)]
        if best:
            yield least(best)

    def cut(best):
        a, b, d = (np.concatenate(c) for c in zip(*best))
        order = np.lexsort((b, d, a))
        a, b, d = a[order], b[order], d[order]
        first = np.maximum.accumulate(np.where(np.append(True, a[1:] != a[:-1]), np.arange(len(a)), 0)) if len(a) else np.arange(0)
        use = np.arange(len(a)) - first < q
        return a[use], b[use], d[use]

    def least(best):
        return pa.RecordBatch.from_arrays([pa.array(c) for c in cut(best)], names=["a", "b", "d2"])

    blocks = written(points.where("v is not null").select(F.col("pid").cast("long").alias("pid"), "v").mapInArrow(packed, "ids binary, v binary").withColumn("k", F.monotonically_increasing_id()), "vector-blocks")
    parts = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    one = blocks.select("k", "ids", "v").repartition(parts, "k")
    near = one.crossJoin(blocks.select(F.col("ids").alias("ids2"), F.col("v").alias("v2"))).mapInArrow(nearest, "a long, b long, d2 double")
    near = near.withColumn("n", F.row_number().over(Window.partitionBy("a").orderBy("d2", "b"))).where(F.col("n") <= q)
    return near.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), F.lit(1.0).alias("ew")).distinct()


def chain_edges(spark, sf_dir) -> DataFrame:
    """Neighbouring turns of a conversation."""
    c = load(spark, sf_dir, "conversations", ["conv_id", "turn"]).select("conv_id", (F.col("conv_id") * 100 + F.col("turn")).alias("src"))
    nxt = F.lead("src").over(Window.partitionBy("conv_id").orderBy("src"))
    return c.select("src", nxt.alias("dst")).where("dst is not null").select("src", "dst", F.lit(1.0).alias("ew"))


def region_edges(spark, sf_dir) -> DataFrame:
    """All pairs of nations in a region, and a ring over the nation keys."""
    n = load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"]).select(F.col("n_nationkey").cast("long").alias("k"), F.col("n_regionkey").alias("r"))
    inside = n.alias("a").join(n.alias("b"), F.col("a.r") == F.col("b.r")).where("a.k < b.k").select(F.col("a.k").alias("src"), F.col("b.k").alias("dst"))
    size = n.agg(F.count("*").alias("size"))
    nxt = F.pmod(F.col("k") + 1, F.col("size"))
    ring = n.crossJoin(F.broadcast(size)).select(F.least("k", nxt).alias("src"), F.greatest("k", nxt).alias("dst"))
    return inside.union(ring).distinct().select("src", "dst", F.lit(1.0).alias("ew"))


def fk_edges(spark, sf_dir) -> DataFrame:
    """Parts and suppliers that share line items; suppliers follow the parts in the vertex numbers."""
    li = load(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey"])
    return li.groupBy("l_partkey", "l_suppkey").agg(F.count("*").cast("double").alias("ew")).select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + 1_000_000_000).alias("dst"), "ew")


def arcs(edges: DataFrame) -> DataFrame:
    """Both directions."""
    return edges.select("src", "dst", "ew").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "ew"))
