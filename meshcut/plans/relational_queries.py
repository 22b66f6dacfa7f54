"""Queries of the operators a user needs around the methods: scans, joins, aggregations, windows, set operations, scalars."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from meshcut.plans import partition_queries as PQ
from meshcut.plans import measured as M
from meshcut.plans import published as B
from meshcut.plans import sqltext as T
from meshcut.plans.registry import ctes, query
from meshcut.sources import meshes, points
from meshcut.operators import measures, relational as R

L2, EV = T.P["lattice2d"], T.P["events2d"]

# -- scans, projections, filters ----------------------------------------------------------------------------------------------


@query("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate < TIMESTAMP '1996-01-01' AND l_quantity > 45")
def scan_pruned(spark, d):
    return points.load(spark, d, "lineitem", ["l_orderkey", "l_quantity"], (F.col("l_shipdate") < F.lit("1996-01-01").cast("timestamp")) & (F.col("l_quantity") > 45))


@query("project_scaled", f"SELECT pid, round((x-min(x) OVER ())/(max(x) OVER ()-min(x) OVER ()), 9) AS x, round((y-min(y) OVER ())/(max(y) OVER ()-min(y) OVER ()), 9) AS y FROM ({EV})")
def project_scaled(spark, d):
    return R.scale(points.events2d(spark, d), ["x", "y"], "range").select("pid", F.round("x", 9).alias("x"), F.round("y", 9).alias("y"))


@query("project_standardised", f"SELECT pid, round((x-a)/s, 6) AS x FROM ({EV}), (SELECT avg(x) AS a, stddev_pop(x) AS s FROM ({EV}))")
def project_standardised(spark, d):
    return R.scale(points.events2d(spark, d), ["x"], "std").select("pid", F.round("x", 6).alias("x"))


@query("box_filter", f"SELECT pid FROM ({L2}) WHERE x BETWEEN 10 AND 20 AND y BETWEEN 5 AND 30")
def box_filter(spark, d):
    return R.in_box(points.lattice2d(spark, d), {"x": (10, 20), "y": (5, 30)}).select("pid")


@query("box_filter_by_curve", f"SELECT pid FROM ({L2}) WHERE x BETWEEN 10 AND 20 AND y BETWEEN 5 AND 30")
def box_filter_by_curve(spark, d):
    """The box as a few key ranges of the sorted curve, then the exact test."""
    p = PQ.lattice_keyed(spark, d)
    return R.in_box(R.in_ranges(p, "hkey", R.curve_ranges((10, 20), (5, 30), 6)), {"x": (10, 20), "y": (5, 30)}).select("pid")


@query("radius_filter", f"SELECT pid FROM ({L2}) WHERE (x-25)*(x-25)+(y-25)*(y-25) <= 100")
def radius_filter(spark, d):
    return R.within(points.lattice2d(spark, d), {"x": 25.0, "y": 25.0}, 10.0).select("pid")


@query("validate_points", f"SELECT (x > 40) AS bad, count(*) AS n FROM ({L2}) GROUP BY 1")
def validate_points(spark, d):
    p = points.lattice2d(spark, d).withColumn("x", F.when(F.col("x") > 40, F.when(F.col("pid") % 2 == 0, F.lit(float("nan")))).otherwise(F.col("x")))
    good, bad = points.check_points(p, ["x", "y"], on_bad="drop")
    return good.agg(F.lit(False).alias("bad"), F.count("*").alias("n")).unionByName(bad.agg(F.lit(True).alias("bad"), F.count("*").alias("n")))


@query("collapse_duplicates", f"SELECT min(pid) AS pid, x, y, sum(w)::BIGINT AS w FROM ({T.P['parts2d']}) GROUP BY x, y")
def collapse_duplicates(spark, d):
    return R.collapse(points.parts2d(spark, d), ["x", "y"])


# -- joins -------------------------------------------------------------------------------------------------------------------


@query("join_centres", f"SELECT p.pid, block, c.x AS cx, c.y AS cy FROM ({T.A8}) p JOIN ({PQ.C8}) c USING (block)")
def join_centres(spark, d):
    c = PQ.sfc_seeds(spark, d).toDF("block", "cx", "cy")
    return PQ.chunks8(spark, d).join(F.broadcast(c), "block").select("pid", "block", "cx", "cy")


SNAPSHOTS = "SELECT (k*20)::DOUBLE AS t, k AS version FROM (SELECT unnest(range(10)) AS k)"


def snapshots(spark):
    return spark.range(10).select((F.col("id") * 20).cast("double").alias("t"), F.col("id").alias("version"))


@query("asof_snapshot", f"SELECT pid, version FROM ({EV}) e ASOF LEFT JOIN ({SNAPSHOTS}) s ON e.x >= s.t")
def asof_snapshot(spark, d):
    return R.as_of(points.events2d(spark, d).select("pid", F.col("x").alias("t")), snapshots(spark), "t", ["version"]).select("pid", "version")


@query("interval_snapshot", f"SELECT pid, version FROM ({EV}) e JOIN ({SNAPSHOTS}) s ON e.x >= s.t AND e.x < s.t+20")
def interval_snapshot(spark, d):
    s = snapshots(spark).select("version", F.col("t").alias("lo"), (F.col("t") + 20).alias("hi"))
    return R.interval_join(points.events2d(spark, d).select("pid", "x"), s, "x", "lo", "hi", 10.0).select("pid", "version")


@query("migration", f"SELECT a.block AS was, b.block AS now, count(*) AS n, sum(w)::BIGINT AS w FROM ({T.A8}) a FULL JOIN (SELECT pid, (pid % 8)::INTEGER AS block FROM ({L2})) b USING (pid) JOIN ({L2}) p USING (pid) GROUP BY ALL")
def migration(spark, d):
    return R.migration(PQ.chunks8(spark, d), PQ.hash_blocks(spark, d), points.lattice2d(spark, d))


REGION_SQL = "SELECT a.n_nationkey::BIGINT AS src, b.n_nationkey::BIGINT AS dst FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey UNION SELECT least(k, n), greatest(k, n) FROM (SELECT n_nationkey::BIGINT AS k, ((n_nationkey+1) % (SELECT count(*) FROM nation))::BIGINT AS n FROM nation)"


@query("two_hop", f"WITH g AS ({REGION_SQL}), e AS (SELECT src, dst FROM g UNION ALL SELECT dst, src FROM g) SELECT DISTINCT a.src, b.dst FROM e a JOIN e b ON a.dst = b.src WHERE a.src < b.dst")
def two_hop(spark, d):
    return R.two_hop(meshes.region_edges(spark, d))


@query("salted_join", "SELECT l_suppkey, s_name, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL")
def salted_join(spark, d):
    li = points.load(spark, d, "lineitem", ["l_suppkey"])
    s = points.load(spark, d, "supplier", ["s_suppkey", "s_name"]).withColumnRenamed("s_suppkey", "l_suppkey")
    return R.salted_join(li, s, "l_suppkey", 8).groupBy("l_suppkey", "s_name").agg(F.count("*").alias("n"))


@query("join_nullsafe", f"WITH t AS ({M.ROWS_SQL}), a AS (SELECT graph, CASE WHEN n > 100000 THEN NULL ELSE n END AS n, method FROM t) SELECT a.graph, a.method, b.method AS other FROM a JOIN a b ON a.n IS NOT DISTINCT FROM b.n AND a.graph = b.graph WHERE a.method < b.method")
def join_nullsafe(spark, d):
    a = M.splits(spark, d).select("graph", F.when(F.col("n") <= 100000, F.col("n")).alias("n"), "method")
    b = a.select(F.col("graph").alias("g2"), F.col("n").alias("n2"), F.col("method").alias("other"))
    return a.join(b, F.col("n").eqNullSafe(F.col("n2")) & (F.col("graph") == F.col("g2"))).where("method < other").select("graph", "method", "other")


# -- aggregations ----------------------------------------------------------------------------------------------------------


@query("adjacency_lists", f"WITH e AS ({T.G1}), a AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) SELECT src AS pid, count(*) AS degree, string_agg(dst::VARCHAR, ' ' ORDER BY dst) AS neighbours FROM a GROUP BY src")
def adjacency_lists(spark, d):
    a = meshes.arcs(PQ.mesh_lattice2d(spark, d)).groupBy(F.col("src").alias("pid")).agg(F.count("*").alias("degree"), F.sort_array(F.collect_list("dst")).alias("l"))
    return a.select("pid", "degree", F.array_join(F.transform("l", lambda x: x.cast("string")), " ").alias("neighbours"))


@query("axis_quantiles", f"SELECT round(quantile_cont(x, 0.25), 6) AS q1, round(quantile_cont(x, 0.5), 6) AS q2, round(quantile_cont(x, 0.75), 6) AS q3 FROM ({EV})")
def axis_quantiles(spark, d):
    p = points.events2d(spark, d)
    return p.agg(*(F.round(F.percentile("x", q), 6).alias(n) for n, q in (("q1", 0.25), ("q2", 0.5), ("q3", 0.75))))


@query("axis_quantiles_sketch")
def axis_quantiles_sketch(spark, d):
    return points.events2d(spark, d).agg(F.percentile_approx("x", [0.25, 0.5, 0.75], 10000).alias("q")).select(F.posexplode("q").alias("k", "x"))


_SUMS = "count(*) AS n, max(total_comm) AS worst"


def _grouped(t, how):
    g = t.rollup("class", "method") if how == "rollup" else t.cube("class", "method")
    return g.agg(F.count("*").alias("n"), F.max("total_comm").alias("worst"))


@query("report_rollup", f"SELECT class, method, {_SUMS} FROM ({B.ROWS_SQL}) GROUP BY ROLLUP (class, method)")
def report_rollup(spark, d):
    return _grouped(B.published(spark), "rollup")


@query("report_cube", f"SELECT class, method, {_SUMS} FROM ({M.ROWS_SQL}) GROUP BY CUBE (class, method)")
def report_cube(spark, d):
    return _grouped(M.splits(spark, d), "cube")


@query("report_grouping_sets", f"SELECT class, method, {_SUMS} FROM ({M.ROWS_SQL}) GROUP BY GROUPING SETS ((class), (method))")
def report_grouping_sets(spark, d):
    g = M.splits(spark, d).groupingSets([["class"], ["method"]], "class", "method")
    return g.agg(F.count("*").alias("n"), F.max("total_comm").alias("worst"))


@query("metric_corr", f"SELECT round(corr(total_comm, cut), 6) AS r, round(corr(total_comm, max_comm), 6) AS r_max FROM ({M.ROWS_SQL})")
def metric_corr(spark, d):
    return M.splits(spark, d).agg(F.round(F.corr("total_comm", "cut"), 6).alias("r"), F.round(F.corr("total_comm", "max_comm"), 6).alias("r_max"))


@query("report_pivot", f"SELECT graph, max(total_comm) FILTER (method='kmeans') AS kmeans, max(total_comm) FILTER (method='hilbert') AS hilbert, max(total_comm) FILTER (method='jagged') AS jagged, max(total_comm) FILTER (method='rcb') AS rcb FROM ({B.ROWS_SQL}) GROUP BY graph")
def report_pivot(spark, d):
    return B.published(spark).groupBy("graph").pivot("method", ["kmeans", "hilbert", "jagged", "rcb"]).agg(F.max("total_comm"))


@query("report_unpivot", f"UNPIVOT (SELECT graph, method, cut, max_comm, total_comm FROM ({B.ROWS_SQL})) ON cut, max_comm, total_comm INTO NAME measure VALUE value")
def report_unpivot(spark, d):
    return B.published(spark).unpivot(["graph", "method"], ["cut", "max_comm", "total_comm"], "measure", "value")


@query("axis_histogram", f"SELECT bin, n, sum(n) OVER (ORDER BY bin)::BIGINT AS upto FROM (SELECT floor(y/2)::BIGINT AS bin, count(*) AS n FROM ({EV}) GROUP BY 1)")
def axis_histogram(spark, d):
    h = points.events2d(spark, d).groupBy(F.floor(F.col("y") / 2).alias("bin")).agg(F.count("*").alias("n"))
    return h.select("bin", "n", F.sum("n").over(Window.orderBy("bin")).alias("upto"))  # one row a bin


@query("histogram_median", f"SELECT round(arg_min(y, (c, y)), 9) AS y FROM (SELECT y, row_number() OVER (ORDER BY y, pid) AS c, count(*) OVER () AS n FROM ({EV})) WHERE 2*c >= n")
def histogram_median(spark, d):
    """Median by refining the bin that holds it: scans of counts, no sort of all rows."""
    return spark.createDataFrame([(round(R.histogram_quantile(points.events2d(spark, d), "y", 0.5), 9),)], "y double")


@query("filtered_agg", f"SELECT method, count(*) FILTER (cut < 1500) AS small_cuts, bool_or(n > 100000) AS any_huge, bool_and(max_comm > 100) AS all_big, mode(class ORDER BY class) AS usual FROM ({M.ROWS_SQL}) GROUP BY method")
def filtered_agg(spark, d):
    return M.splits(spark, d).groupBy("method").agg(F.count_if(F.col("cut") < 1500).alias("small_cuts"), F.bool_or(F.col("n") > 100000).alias("any_huge"), F.bool_and(F.col("max_comm") > 100).alias("all_big"), F.mode("class", deterministic=True).alias("usual"))


# -- windows ---------------------------------------------------------------------------------------------------------------


@query("rank_methods", f"SELECT graph, method, rank() OVER w AS rank, dense_rank() OVER w AS dense, row_number() OVER (PARTITION BY graph ORDER BY total_comm, method) AS position FROM ({M.ROWS_SQL}) WINDOW w AS (PARTITION BY graph ORDER BY total_comm)")
def rank_methods(spark, d):
    w, total = (Window.partitionBy("graph").orderBy("total_comm", *more) for more in ((), ("method",)))
    return M.splits(spark, d).select("graph", "method", *(f().over(v).cast("long").alias(n) for f, v, n in ((F.rank, w, "rank"), (F.dense_rank, w, "dense"), (F.row_number, total, "position"))))


@query("ntile_chunks", f"SELECT pid, (ntile(8) OVER (ORDER BY hkey, pid)-1)::INTEGER AS block FROM ({T.H2})")
def ntile_chunks(spark, d):
    """Equal-count chunks: the first n mod k chunks have one more, by global ranks instead of one window over all rows."""
    from meshcut.operators import ranks

    r = ranks.global_rank(PQ.lattice_keyed(spark, d))
    n = r.agg(F.count("*").alias("n"))
    long, rest = F.floor(F.col("n") / 8) + 1, F.col("n") % 8
    block = F.when(F.col("rank") < rest * long, F.floor(F.col("rank") / long)).otherwise(rest + F.floor((F.col("rank") - rest * long) / (long - 1)))
    return r.crossJoin(F.broadcast(n)).select("pid", block.cast("int").alias("block"))


@query("curve_steps", f"SELECT pid, abs(gx-lag(gx) OVER w)+abs(gy-lag(gy) OVER w) AS step FROM ({T.H2}) WINDOW w AS (PARTITION BY hkey >> 6 ORDER BY hkey)")
def curve_steps(spark, d):
    w = Window.partitionBy(F.shiftright("hkey", 6)).orderBy("hkey")
    return PQ.lattice_keyed(spark, d).select("pid", (F.abs(F.col("gx") - F.lag("gx").over(w)) + F.abs(F.col("gy") - F.lag("gy").over(w))).alias("step"))


@query("range_frame_density", f"SELECT pid, count(*) OVER (PARTITION BY floor(y/5) ORDER BY x RANGE BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS near FROM ({EV})")
def range_frame_density(spark, d):
    return R.near_counts(points.events2d(spark, d), F.floor(F.col("y") / 5), "x")


@query("curve_position", f"SELECT pid, round(percent_rank() OVER w, 9) AS share, round(cume_dist() OVER w, 9) AS upto FROM ({T.H2}) WINDOW w AS (PARTITION BY gx ORDER BY hkey)")
def curve_position(spark, d):
    w = Window.partitionBy("gx").orderBy("hkey")
    return PQ.lattice_keyed(spark, d).select("pid", F.round(F.percent_rank().over(w), 9).alias("share"), F.round(F.cume_dist().over(w), 9).alias("upto"))


@query("rolling_load", "SELECT user_id, event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 6 PRECEDING AND CURRENT ROW), 6) AS load FROM events")
def rolling_load(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-6, 0)
    return points.load(spark, d, "events", ["user_id", "event_id", "ts", "value"]).select("user_id", "event_id", F.round(F.avg("value").over(w), 6).alias("load"))


# -- top-k, pages, set operations ---------------------------------------------------------------------------------------------


@query("top_blocks", f"SELECT block, weight FROM ({PQ.W8}) ORDER BY weight DESC, block LIMIT 3")
def top_blocks(spark, d):
    return PQ.block_weights(spark, d).orderBy(F.desc("weight"), "block").limit(3)


@query("report_page", f"SELECT graph, method, total_comm FROM ({B.ROWS_SQL}) ORDER BY total_comm, method LIMIT 5 OFFSET 5")
def report_page(spark, d):
    return B.published(spark).select("graph", "method", "total_comm").orderBy("total_comm", "method").offset(5).limit(5)


@query("merge_edges", f"WITH e AS ({T.G1}) SELECT src, dst FROM e UNION SELECT src, dst FROM e WHERE src % 2 = 0 UNION SELECT 1::BIGINT, 2::BIGINT")
def merge_edges(spark, d):
    e = PQ.mesh_lattice2d(spark, d).select("src", "dst")
    return e.union(e.where("src % 2 = 0")).union(spark.range(1).select(F.lit(1).cast("long"), F.lit(2).cast("long"))).distinct()


CUT_H = f"SELECT src, dst FROM ({T.E8}) WHERE b1 <> b2"
CUT_X = f"SELECT src, dst FROM ({T.G1}) WHERE src % 8 <> dst % 8"


def two_cuts(spark, d):
    e = PQ.mesh_lattice2d(spark, d)
    return (measures.cut_edges(e, a).select("src", "dst") for a in (PQ.chunks8(spark, d), PQ.hash_blocks(spark, d)))


@query("cut_intersect", f"{CUT_H} INTERSECT {CUT_X}")
def cut_intersect(spark, d):
    a, b = two_cuts(spark, d)
    return a.intersect(b)


@query("cut_except", f"{CUT_X} EXCEPT {CUT_H}")
def cut_except(spark, d):
    a, b = two_cuts(spark, d)
    return b.subtract(a)


@query("cut_except_all", f"{CUT_X} EXCEPT ALL {CUT_H}")
def cut_except_all(spark, d):
    a, b = two_cuts(spark, d)
    return b.exceptAll(a)


# -- scalar functions ------------------------------------------------------------------------------------------------------------


@query("scalar_math", f"SELECT pid, round(sqrt(x), 9) AS a, round(cbrt(y+1), 9) AS b, round(exp(-x/10), 9) AS c, round(ln(1+y), 9) AS d, floor(y/3)::BIGINT AS e, greatest(x, y) AS f, (pid*7+3) % 11 AS g, round(pow(x, 0.5::DOUBLE), 9) AS h, CASE WHEN y = 0 THEN NULL ELSE x/y END AS i FROM ({EV})")
def scalar_math(spark, d):
    return points.events2d(spark, d).selectExpr("pid", "round(sqrt(x), 9) AS a", "round(cbrt(y+1), 9) AS b", "round(exp(-x/10), 9) AS c", "round(ln(1+y), 9) AS d", "floor(y/3) AS e", "greatest(x, y) AS f", "pmod(pid*7+3, 11) AS g", "round(pow(x, 0.5D), 9) AS h", "try_divide(x, y) AS i")


@query("scalar_bits", f"SELECT pid, pid << 3 AS a, pid >> 2 AS b, pid & 255 AS c, pid | 15 AS d, xor(pid, 1023) AS e, bit_count(pid)::INTEGER AS f FROM ({L2})")
def scalar_bits(spark, d):
    return points.lattice2d(spark, d).selectExpr("pid", "shiftleft(pid, 3) AS a", "shiftright(pid, 2) AS b", "pid & 255 AS c", "pid | 15 AS d", "pid ^ 1023 AS e", "bit_count(pid) AS f")


@query("scalar_dates", "SELECT event_id, date_diff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS days, epoch_us(date_trunc('hour', ts)) AS hour_us, hour(ts)::INTEGER AS h, epoch_us(ts + INTERVAL 36 HOUR) AS later_us FROM events")
def scalar_dates(spark, d):
    return points.load(spark, d, "events").selectExpr("event_id", "datediff(ts, DATE'2024-01-01') AS days", "unix_micros(CAST(date_trunc('HOUR', ts) AS TIMESTAMP)) AS hour_us", "hour(ts) AS h", "unix_micros(CAST(ts + INTERVAL '36' HOUR AS TIMESTAMP)) AS later_us")


@query("scalar_strings", "SELECT page_id, length(url)::INTEGER AS n, len(string_split(url, '/'))::INTEGER AS parts, regexp_extract(url, '^[a-z]+', 0) AS scheme, lower(substring(url, 1, 12)) AS head, url || '#' || page_id AS tag FROM pages")
def scalar_strings(spark, d):
    return points.load(spark, d, "pages", ["page_id", "url"]).selectExpr("page_id", "length(url) AS n", "size(split(url, '/')) AS parts", "regexp_extract(url, '^[a-z]+', 0) AS scheme", "lower(substring(url, 1, 12)) AS head", "concat_ws('#', url, page_id) AS tag")


@query("scalar_arrays", "SELECT vec_id, len(embedding)::INTEGER AS n, round(list_min(embedding)::DOUBLE, 6) AS least, round(embedding[3]::DOUBLE, 6) AS third, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS positive, round(list_sum(list_transform(embedding[1:4], lambda x: x::DOUBLE)), 6) AS head FROM embeddings")
def scalar_arrays(spark, d):
    return points.load(spark, d, "embeddings").selectExpr("vec_id", "size(embedding) AS n", "round(CAST(array_min(embedding) AS DOUBLE), 6) AS least", "round(CAST(element_at(embedding, 3) AS DOUBLE), 6) AS third", "size(filter(embedding, x -> x > 0)) AS positive", "round(aggregate(transform(slice(embedding, 1, 4), x -> CAST(x AS DOUBLE)), 0D, (s, x) -> s + x), 6) AS head")


@query("vector_distance", "SELECT a.vec_id, round(sqrt(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: (p[1]::DOUBLE-p[2])*(p[1]::DOUBLE-p[2])))), 6) AS dist FROM embeddings a, (SELECT embedding FROM embeddings WHERE vec_id = 0) b")
def vector_distance(spark, d):
    e = points.embeddings(spark, d)
    first = e.where("pid = 0").select(F.col("v").alias("u"))  # one row
    d2 = F.aggregate(F.zip_with("v", "u", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    return e.crossJoin(F.broadcast(first)).select(F.col("pid").alias("vec_id"), F.round(F.sqrt(d2), 6).alias("dist"))


@query("metrics_map", f"SELECT graph, method, value FROM ({M.ROWS_SQL}) t, LATERAL (SELECT round(total_comm/cut, 6) AS value) WHERE total_comm/cut > 0.5")
def metrics_map(spark, d):
    """Measures of a graph as a map by method, transformed, filtered and exploded again."""
    t = M.splits(spark, d).groupBy("graph").agg(F.map_from_entries(F.collect_list(F.struct("method", "total_comm"))).alias("a"), F.map_from_entries(F.collect_list(F.struct("method", "cut"))).alias("b"))
    ratio = F.map_filter(F.map_zip_with("a", "b", lambda k, x, y: F.round(x / y, 6)), lambda k, v: v > 0.5)
    return t.select("graph", F.explode(ratio).alias("method", "value"))


@query("struct_order", f"SELECT graph, arg_min(method, (total_comm, method)) AS best FROM ({B.ROWS_SQL}) GROUP BY graph")
def struct_order(spark, d):
    return B.published(spark).groupBy("graph").agg(F.min(F.struct("total_comm", "method"))["method"].alias("best"))


@query("events_json_weight", "SELECT event_id, (props->>'$.k')::BIGINT AS w FROM events")
def events_json_weight(spark, d):
    return points.load(spark, d, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k long")["k"].alias("w"))


@query("scalar_casts", "SELECT page_id, TRY_CAST(regexp_extract(url, '[0-9]+', 0) AS INTEGER) AS number, page_id::VARCHAR AS text, page_id::DOUBLE AS real FROM pages")
def scalar_casts(spark, d):
    return points.load(spark, d, "pages", ["page_id", "url"]).selectExpr("page_id", "try_cast(regexp_extract(url, '[0-9]+', 0) AS INT) AS number", "CAST(page_id AS STRING) AS text", "CAST(page_id AS DOUBLE) AS real")
