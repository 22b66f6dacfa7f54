"""The experiments that compare methods: random triangulations, class ratios, scaling, component shares, shapes, density.

Reports and scaling runs have a handful of rows; a session keeps them by table folder, so that an experiment that is computed
from another's rows does not run it again.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.operators import baselines, kmeans, measures, ranks
from meshcut.plans import measure_queries as MQ
from meshcut.plans import partition_queries as PQ
from meshcut.plans import sqltext as T
from meshcut.plans import workloads
from meshcut.plans.registry import QUERIES, query
from meshcut.sources import meshes, points
from meshcut.sources.scratch import written

_ROWS: dict = {}


def kept(spark: SparkSession, d: str, name: str, make) -> DataFrame:
    """make()'s few rows, computed once a session and folder."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _ROWS:
        df = make()
        _ROWS[key] = (df.collect(), df.schema)
    return spark.createDataFrame(*_ROWS[key])


# -- random planar triangulations ----------------------------------------------------------------------------------------

JITTERED = "SELECT pid, gx, gy, (gx*2500 + pid*7919 % 1000)/2500.0::DOUBLE AS x, (gy*2500 + pid*104729 % 1000)/2500.0::DOUBLE AS y, w FROM ({p})".format(p=T.P["lattice2d"])


def _in_circle(a, b, c, p):
    """Positive if p is inside the circle through a, b, c (counter-clockwise), as text for either dialect."""
    (ax, ay), (bx, by), (cx, cy) = ((f"({q}_x-{p}_x)", f"({q}_y-{p}_y)") for q in (a, b, c))
    return f"({ax}*{ax}+{ay}*{ay})*({bx}*{cy}-{cx}*{by}) - ({bx}*{bx}+{by}*{by})*({ax}*{cy}-{cx}*{ay}) + ({cx}*{cx}+{cy}*{cy})*({ax}*{by}-{bx}*{ay})"


_CORNERS = (("a", 0, 0), ("b", 1, 0), ("c", 1, 1), ("d", 0, 1))
_CELLS = (
    "SELECT " + ", ".join(f"{n}.pid AS {n}, {n}.X AS {n}_x, {n}.Y AS {n}_y" for n, _, _ in _CORNERS) + " FROM q a"
    + "".join(f" JOIN q {n} ON {n}.gx = a.gx+{i} AND {n}.gy = a.gy+{j}" for n, i, j in _CORNERS[1:])
)
TRIANGULATED = T.materialized(
    [("q", f"SELECT pid, gx, gy, gx*2500 + pid*7919 % 1000 AS X, gy*2500 + pid*104729 % 1000 AS Y FROM ({T.P['lattice2d']})"), ("cells", _CELLS)],
    f"SELECT a.pid AS src, b.pid AS dst, 1.0::DOUBLE AS ew FROM q a JOIN q b ON (b.gx = a.gx+1 AND b.gy = a.gy) OR (b.gx = a.gx AND b.gy = a.gy+1) UNION ALL SELECT CASE WHEN {_in_circle('a', 'b', 'c', 'd')} > 0 THEN d ELSE a END, CASE WHEN {_in_circle('a', 'b', 'c', 'd')} > 0 THEN b ELSE c END, 1.0::DOUBLE FROM cells",
)


def jittered(spark, d) -> DataFrame:
    """Lattice cells, each at a place of its own inside the cell."""
    p = points.lattice2d(spark, d)
    x, y = (F.col(g) * 2500 + (F.col("pid") * m) % 1000 for g, m in (("gx", 7919), ("gy", 104729)))
    return p.select("pid", "gx", "gy", (x / 2500).alias("x"), (y / 2500).alias("y"), "w")


@query("mesh_triangulated", TRIANGULATED)
def mesh_triangulated(spark, d):
    """Planar triangulation of scattered points: neighbours along both axes, and in each cell the diagonal of the two that
    leaves no corner inside the circle of the others. Cells join by their numbers; no task holds more than a cell."""
    p = points.lattice2d(spark, d)
    q = p.select("pid", "gx", "gy", (F.col("gx") * 2500 + (F.col("pid") * 7919) % 1000).alias("X"), (F.col("gy") * 2500 + (F.col("pid") * 104729) % 1000).alias("Y"))
    sides = [w for w in ((1, 0), (0, 1))]
    cells = q.select(F.col("pid").alias("a"), F.col("X").alias("a_x"), F.col("Y").alias("a_y"), F.col("gx").alias("_i"), F.col("gy").alias("_j"))
    for n, i, j in _CORNERS[1:]:
        corner = q.select(F.col("pid").alias(n), F.col("X").alias(f"{n}_x"), F.col("Y").alias(f"{n}_y"), (F.col("gx") - i).alias("_i"), (F.col("gy") - j).alias("_j"))
        cells = cells.join(corner, ["_i", "_j"])
    swap = F.expr(_in_circle("a", "b", "c", "d")) > 0
    diagonal = cells.select(F.when(swap, F.col("d")).otherwise(F.col("a")).alias("src"), F.when(swap, F.col("b")).otherwise(F.col("c")).alias("dst"), F.lit(1.0).alias("ew"))
    out = diagonal
    for i, j in sides:
        other = q.select(F.col("pid").alias("dst"), (F.col("gx") - i).alias("gx"), (F.col("gy") - j).alias("gy"))
        out = out.unionByName(q.join(other, ["gx", "gy"]).select(F.col("pid").alias("src"), "dst", F.lit(1.0).alias("ew")))
    return out


_parts, _blocks = MQ.report_methods_sql(T.hilbert2d(JITTERED, 6), JITTERED, 8)


@query("w5_report", MQ.report_sql(_parts, JITTERED, TRIANGULATED, _blocks, 8))
def w5_report(spark, d):
    """Random planar triangulation."""
    p = jittered(spark, d)
    keyed = p.join(PQ.lattice_keyed(spark, d).select("pid", "hkey"), "pid")
    return MQ.report(p, mesh_triangulated(spark, d), MQ.report_methods(p, keyed, PQ.XY, 8), 8)


# -- ratios to the method, by class of graph ------------------------------------------------------------------------------

CLASSES = {"w1_report": "2d", "w4_report": "2d", "w5_report": "2d", "w2_report": "2.5d", "w3_report": "3d"}
MEASURES = ("cut", "max_comm", "total_comm")


def _shared(name: str) -> None:
    """A report that a session has shown is not computed again for the ratios."""
    run = QUERIES[name]
    QUERIES[name] = lambda spark, d: kept(spark, d, name, lambda: run(spark, d))


for _name in CLASSES:
    _shared(_name)


def _ratios_sql() -> str:
    from meshcut.plans.registry import ORACLES

    every = " UNION ALL ".join(f"SELECT '{c}' AS class, '{n}' AS graph, method, {', '.join(MEASURES)} FROM ({ORACLES[n]})" for n, c in CLASSES.items())
    ratios = ", ".join(f"round(exp(avg(ln(a.{m}::DOUBLE/b.{m}))), 6) AS {m}" for m in MEASURES)
    return f"WITH t AS MATERIALIZED ({every}) SELECT a.class, a.method, {ratios} FROM t a JOIN t b ON a.graph = b.graph AND b.method = 'kmeans' WHERE a.method <> 'kmeans' GROUP BY ALL"


@query("w6_class_ratios", _ratios_sql())
def w6_class_ratios(spark, d):
    """Each baseline's measures over those of balanced k-means, geometric means by class of graph."""
    # the reports' many short jobs fill the cores only side by side
    with ThreadPoolExecutor(len(CLASSES)) as pool:
        reports = list(pool.map(inheritable_thread_target(spark)(lambda name: QUERIES[name](spark, d)), CLASSES))
    rows = [r.select(F.lit(cls).alias("class"), F.lit(name).alias("graph"), "method", *MEASURES) for r, (name, cls) in zip(reports, CLASSES.items())]
    every = reduce(DataFrame.unionByName, rows)
    return measures.ratio_table(every, "kmeans", list(MEASURES))


# -- shapes and density ---------------------------------------------------------------------------------------------------

_parts, _blocks = MQ.report_methods_sql(T.H2, T.P["lattice2d"], 8)
_aspect = "SELECT '{m}' AS method, round(avg(greatest(ex, ey)/least(ex, ey)), 6) AS aspect, round(max(greatest(ex, ey)/least(ex, ey)), 6) AS longest FROM (SELECT max(x)-min(x) AS ex, max(y)-min(y) AS ey FROM kp JOIN ({a}) USING (pid) GROUP BY block) WHERE least(ex, ey) > 0"


@query("w12_eight_blocks", T.materialized(_parts, " UNION ALL ".join(_aspect.format(m=m, a=a) for m, a in _blocks.items())))
def w12_eight_blocks(spark, d):
    """The shapes of eight blocks by each method: mean and largest ratio of the sides of their boxes."""
    p = points.lattice2d(spark, d)
    out = None
    for m, a in MQ.report_methods(p, PQ.lattice_keyed(spark, d), PQ.XY, 8).items():
        row = measures.block_aspect(p, a).where("aspect is not null").agg(F.round(F.avg("aspect"), 6).alias("aspect"), F.round(F.max("aspect"), 6).alias("longest")).select(F.lit(m).alias("method"), "aspect", "longest")
        out = row if out is None else out.unionByName(row)
    return out


def _density_sql() -> str:
    src, rows, parts = T.P["orders2d"], [], []
    for name, erosion in (("with", True), ("without", False)):
        # each choice has CTEs of its own
        mine = PQ.kmeans_sql(src, PQ.sorted_seeds(src, "xy"), 8, erosion=erosion)
        sql = T.materialized(mine, "SELECT kp.w, b.block FROM kmeans_blocks b JOIN kp USING (pid)")
        rows.append(f"SELECT '{name}' AS erosion, round(max(s)/(sum(s)/8.0::DOUBLE)-1, 6) AS imbalance FROM (SELECT sum(w)::DOUBLE AS s FROM ({sql}) GROUP BY block)")
    return " UNION ALL ".join(rows)


@query("w16_density", _density_sql())
def w16_density(spark, d):
    """Points of uneven density and weight, with and without erosion of influence, after the same rounds."""
    p = points.orders2d(spark, d)
    out = None
    for name, erosion in (("with", True), ("without", False)):
        a = kmeans.balanced_kmeans(p, 8, erosion=erosion, **PQ.FIXED).assignment
        sizes = p.join(a, "pid").groupBy("block").agg(F.sum("w").cast("double").alias("s"))
        row = sizes.agg(F.round(F.max("s") / (F.sum("s") / 8) - 1, 6).alias("imbalance")).select(F.lit(name).alias("erosion"), "imbalance")
        out = row if out is None else out.unionByName(row)
    return out


@query("w17_disconnected")
def w17_disconnected(spark, d):
    """Blocks that fall into pieces on a geometric graph, by method: their number, and the pieces of the worst."""
    p = written(points.events2d(spark, d), "cloud")
    edges = meshes.radius_edges(p, 0.5)
    out = None
    for m in ("kmeans", "hilbert", "rcb", "hash"):
        a = written(workloads.run_method(m, p, 8, ["x", "y"], **({"max_iter": 8, "stop": "balance"} if m == "kmeans" else {})), "blocks")
        row = measures.components(edges, a).agg(F.count_if(F.col("n") > 1).alias("broken"), F.max("n").alias("pieces")).select(F.lit(m).alias("method"), "broken", "pieces")
        out = row if out is None else out.unionByName(row)
    return out


@query("w19_vectors")
def w19_vectors(spark, d):
    """Balanced k-means of the embeddings in all their dimensions; the curve sort takes the first three."""
    e = points.embeddings(spark, d)
    n = len(e.select("v").first()[0])
    dims = [f"v{i}" for i in range(n)]
    p = written(e.select("pid", *(F.get("v", F.lit(i)).alias(c) for i, c in enumerate(dims)), F.lit(1).cast("long").alias("w")), "vectors")
    rows = []
    for name, more in (("balanced", {}), ("plain", {"balance": False})):
        r = kmeans.balanced_kmeans(p, 10, dims=dims, curve_dims=dims[:3], max_iter=2, max_balance=3, sample_start=None, engine="tile", **more)
        sse = kmeans.sse(r.assignment.join(p, "pid"), r.centres, dims).first()[0]
        rows.append((name, float(r.imbalance), float(sse), r.rounds))
    return spark.createDataFrame(rows, "method string, imbalance double, sse double, rounds int")


# -- scaling --------------------------------------------------------------------------------------------------------------

SCALING = "method string, p int, n long, k int, seconds double, index double, seeds double, rounds double"


def scaling(spark: SparkSession, d: str, growing: bool, workers=(2, 4, 8)) -> DataFrame:
    """Seconds of methods over p partitions; growing: points in proportion to p (weak scaling), else always all of them.
    Balanced k-means' are also given by part. One machine has a fixed number of cores, so p is the number of partitions."""
    cloud = written(points.events2d(spark, d), "cloud")
    n = cloud.count()
    before = spark.conf.get("spark.sql.shuffle.partitions")
    rows = []
    try:
        for p in workers:
            size = n * p // workers[-1] if growing else n
            some = written(cloud.where(kmeans.in_sample(size, n)) if size < n else cloud, "cloud")
            m = some.count()
            spark.conf.set("spark.sql.shuffle.partitions", str(p))
            for method in ("kmeans", "hilbert", "rcb"):
                began = time.perf_counter()
                if method == "kmeans":
                    r = kmeans.balanced_kmeans(some, p, max_iter=4, max_balance=6, stop="balance")
                    r.assignment.write.format("noop").mode("overwrite").save()
                    parts = [float(r.counters[f"seconds_{x}"]) for x in ("index", "seeds", "rounds")]
                else:
                    workloads.run_method(method, some, p, ["x", "y"]).write.format("noop").mode("overwrite").save()
                    parts = [None] * 3
                rows.append((method, p, m, p, time.perf_counter() - began, *parts))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    return spark.createDataFrame(rows, SCALING)


@query("w9_weak_scaling")
def w9_weak_scaling(spark, d):
    return kept(spark, d, "w9", lambda: scaling(spark, d, True))


@query("w10_fixed_scaling")
def w10_fixed_scaling(spark, d):
    return kept(spark, d, "w10", lambda: scaling(spark, d, False))


@query("w11_component_shares")
def w11_component_shares(spark, d):
    """Shares of balanced k-means' time: curve index and redistribution, seeds, rounds."""
    r = w9_weak_scaling(spark, d).where("method = 'kmeans'")
    return r.select("p", *(F.round(F.col(c) / F.col("seconds"), 4).alias(c) for c in ("index", "seeds", "rounds")))


@query("w13_own_trend")
def w13_own_trend(spark, d):
    """The trend of time against points over the runs of both scalings."""
    rows = w9_weak_scaling(spark, d).unionByName(w10_fixed_scaling(spark, d))
    return measures.fit_trend(rows)


# -- tables of results ----------------------------------------------------------------------------------------------------


@query("w8_results")
def w8_results(spark, d):
    """One row a method, converged: time, cut, communication, diameter, time of a sparse product, on a geometric graph."""
    return workloads.run(spark, "w4", d, methods=("kmeans", "hilbert", "jagged", "rcb", "rib"), ks=(16,), products=3)
