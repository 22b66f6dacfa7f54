"""Runs a workload: point set and mesh, every method, all measures and the seconds each method took."""

from __future__ import annotations

import time
from statistics import mean

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshcut.operators import baselines, kmeans, measures, ranks
from meshcut.plans.registry import query
from meshcut.sources import meshes, points
from meshcut.sources.scratch import written

#: Workload -> (point set, dimensions, mesh, unweighted). Mesh: lattice cells, or the radius of a geometric graph.
SETS = {
    "w1": ("lattice2d", ["x", "y"], ["gx", "gy"], True),
    "w2": ("lattice2d", ["x", "y"], ["gx", "gy"], False),
    "w3": ("lattice3d", ["x", "y", "z"], ["gx", "gy", "gz"], True),
    "w4": ("events2d", ["x", "y"], 0.3, True),
}
METHODS = ("kmeans", "hilbert", "morton", "jagged", "rcb", "rib", "lloyd", "hash")
REPORT = "workload string, method string, k int, cut double, max_comm long, total_comm long, harm_diam double, imbalance double, ghosts long, aspect double, seconds double, product_seconds double"


def run_method(method: str, p: DataFrame, k: int, dims: list[str], **more) -> DataFrame:
    """(pid, block) of a method by name."""
    if method == "kmeans":
        return kmeans.balanced_kmeans(p, k, dims=dims, **more).assignment.select("pid", "block")
    if method == "lloyd":
        return baselines.lloyd(p, k, 10, dims=dims).assignment.select("pid", "block")
    if method in ("hilbert", "morton"):
        return baselines.curve_chunks(ranks.spatial_sort(p, dims, curve=method), k)
    if method == "jagged":
        return baselines.jagged_sections(p, baselines.jagged_parts(k, len(dims)), dims)
    if method == "rcb":
        return baselines.coordinate_bisection(p, k, dims)
    if method == "rib":
        return baselines.inertial_bisection(p, k, dims)
    return baselines.hash_blocks(p, k)


def inputs(spark, wid: str, sf_dir: str) -> tuple[DataFrame, DataFrame, list[str]]:
    name, dims, mesh, plain = SETS[wid]
    p = getattr(points, name)(spark, sf_dir)
    if plain:
        p = p.withColumn("w", F.lit(1).cast("long"))
    edges = meshes.radius_edges(p, mesh, dims) if isinstance(mesh, float) else meshes.lattice_edges(p, mesh, weighted=not plain)
    return written(p, "points"), written(edges, "edges"), dims


def run(spark, wid: str, sf_dir: str, methods=METHODS, ks=(8,), repeat: int = 1, diameters: bool = True, products: int = 0) -> DataFrame:
    """One report row a method and k; seconds are the mean of `repeat` runs, each ended by writing the assignment;
    product_seconds the mean of so many sparse products (null for none)."""
    p, edges, dims = inputs(spark, wid, sf_dir)
    rows = []
    for k in ks:
        for m in methods:
            took = []
            for _ in range(repeat):
                began = time.perf_counter()
                a = written(run_method(m, p, k, dims), "blocks")
                took.append(time.perf_counter() - began)
            cut = measures.edge_cut(edges, a, weighted=True).first()[0]
            comm = measures.comm_summary(measures.comm_volume(edges, a)).first()
            diam = measures.harm_diam(measures.block_diameters(edges, a)).first()[0] if diameters else None
            loads = [r["s"] for r in p.join(a, "pid").groupBy("block").agg(F.sum("w").cast("double").alias("s")).collect()]
            imb = kmeans.imbalance(loads, [sum(loads) / k] * len(loads))
            ghosts = measures.boundary_vertices(edges, a).count()
            aspect = measures.block_aspect(p, a, dims).agg(F.avg("aspect")).first()[0]
            vec = p.select("pid", F.lit(1.0).alias("val"))
            product = measures.time_spmv(edges, a, vec, products) if products else None
            rows.append((wid, m, k, float(cut), comm[0], comm[1], diam, float(imb), ghosts, aspect, mean(took), product))
    return spark.createDataFrame(rows, REPORT)


@query("w14_tolerance")
def w14_tolerance(spark, d):
    """Balance at a tolerance of 3 and 5 per cent, in the plane and in space, with weights."""
    rows = []
    for name, dims in (("lattice2d", ["x", "y"]), ("lattice3d", ["x", "y", "z"])):
        p = written(getattr(points, name)(spark, d), "points")
        for eps in (0.03, 0.05):
            r = kmeans.balanced_kmeans(p, 8, dims=dims, eps=eps, max_iter=12, stop="balance")
            rows.append((name, eps, r.balanced, float(r.imbalance), r.rounds, r.passes))
    return spark.createDataFrame(rows, "points string, eps double, balanced boolean, imbalance double, rounds int, passes int")


@query("w15_ablation")
def w15_ablation(spark, d):
    """Bounds, boxes, sampling, erosion and curve seeds switched off one at a time: effort, balance and quality."""
    p = written(points.lattice2d(spark, d), "points")
    edges = written(meshes.lattice_edges(p, ["gx", "gy"]), "edges")
    switches = {"all": {}, "no_bounds": {"bounds": False}, "tile_engine": {"engine": "tile"}, "no_sampling": {"sample_start": None}, "no_erosion": {"erosion": False}, "random_seeds": {"seed": "random"}}
    rows = []
    for name, s in switches.items():
        r = kmeans.balanced_kmeans(p, 8, max_iter=8, stop="balance", **s)
        a = written(r.assignment, "blocks")
        sse = kmeans.sse(p.join(a.select("pid", "block"), "pid"), r.centres, ["x", "y"]).first()[0]
        comm = measures.comm_summary(measures.comm_volume(edges, a.select("pid", "block"))).first()
        rows.append((name, r.balanced, float(r.imbalance), r.rounds, r.passes, float(r.counters["skip_rate"]), float(r.counters["centres_per_point"]), float(sse), comm[1]))
    return spark.createDataFrame(rows, "switch string, balanced boolean, imbalance double, rounds int, passes int, skip_rate double, centres_per_point double, sse double, total_comm long")
