"""Graph measures of a partition: cut, external edges, communication volume, diameters, SpMV exchange, shape, trends."""

from __future__ import annotations

import itertools
import time
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from meshcut.functions.geometry import geometric_mean, harmonic_mean
from meshcut.sources.meshes import arcs


def edge_blocks(edges: DataFrame, a: DataFrame) -> DataFrame:
    """edges with the blocks of both ends, b1 and b2: two equi joins."""
    one = a.select(F.col("pid").alias("src"), F.col("block").alias("b1"))
    two = a.select(F.col("pid").alias("dst"), F.col("block").alias("b2"))
    return edges.join(one, "src").join(two, "dst").select("src", "dst", "ew", "b1", "b2")


def cut_edges(edges: DataFrame, a: DataFrame) -> DataFrame:
    return edge_blocks(edges, a).where("b1 <> b2")


def external_edges(edges: DataFrame, a: DataFrame) -> DataFrame:
    """(block, ext): edges that leave each block that has any."""
    ends = cut_edges(edges, a).select(F.explode(F.array("b1", "b2")).alias("block"))
    return ends.groupBy("block").agg(F.count("*").alias("ext"))


def edge_cut(edges: DataFrame, a: DataFrame, weighted: bool = False) -> DataFrame:
    cut = cut_edges(edges, a)
    return cut.agg((F.coalesce(F.sum("ew"), F.lit(0.0)) if weighted else F.count("*")).alias("cut"))


def border(edges: DataFrame, a: DataFrame, include_own: bool = False) -> DataFrame:
    """Distinct (block, pid, other): a vertex of block that is next to block `other`."""
    e = edge_blocks(edges, a)
    e = e if include_own else e.where("b1 <> b2")
    one = e.select(F.col("b1").alias("block"), F.col("src").alias("pid"), F.col("b2").alias("other"))
    two = e.select(F.col("b2").alias("block"), F.col("dst").alias("pid"), F.col("b1").alias("other"))
    return one.unionByName(two).distinct()


def comm_volume(edges: DataFrame, a: DataFrame, include_own: bool = False, approx: float | None = None) -> DataFrame:
    """(block, comm): over the block's vertices, the number of other blocks each is next to. approx: relative error."""
    b = border(edges, a, include_own)
    if approx:
        cut = cut_edges(edges, a)
        pairs = cut.select(F.col("b1").alias("block"), F.struct("src", "b2").alias("v")).unionByName(cut.select(F.col("b2").alias("block"), F.struct(F.col("dst").alias("src"), F.col("b1").alias("b2")).alias("v")))
        return pairs.groupBy("block").agg(F.approx_count_distinct(F.xxhash64("v"), approx).alias("comm"))
    return b.groupBy("block").agg(F.count("*").alias("comm"))


def comm_summary(comm: DataFrame) -> DataFrame:
    return comm.agg(F.coalesce(F.max("comm"), F.lit(0)).alias("max_comm"), F.coalesce(F.sum("comm"), F.lit(0)).alias("total_comm"))


def radius_cuts(p: DataFrame, r: float, names: list[str], k: int, dims=("x", "y")) -> DataFrame:
    """(method, block, ends, comm) on the graph of all pairs at most r apart, by each of the block columns `names`: ends of cut
    edges in the block, and its communication volume. p: pid, dims and the columns, blocks below k.

    No edge is a row: points are dealt to grid cells of side r and to the cells around theirs, so a cell holds all neighbours
    of its points, and counts them by block in products of a hit matrix with the blocks of the others.
    """
    near = F.array(*(F.struct(*(F.lit(s).alias(f"s{n}") for n, s in enumerate(w)), F.lit(not any(w)).alias("mine")) for w in itertools.product((-1, 0, 1), repeat=len(dims))))
    dealt = p.select(*dims, *names, F.inline(near))
    dealt = dealt.select(*((F.floor(F.col(d) / r).cast("long") + F.col(f"s{n}")).alias(f"k{n}") for n, d in enumerate(dims)), "mine", *(F.col(d).cast("double").alias(d) for d in dims), *(F.col(c).cast("int").alias(c) for c in names))
    keys = [f"k{n}" for n in range(len(dims))]
    size = len(dims)

    def run(batches):
        ends, comm = np.zeros((len(names), k), np.int64), np.zeros((len(names), k), np.int64)

        def add(held):
            mine, *cols = (np.concatenate(c) for c in zip(*held))
            at = np.nonzero(mine)[0]
            if not len(at):
                return
            x, blocks = cols[:size], np.stack(cols[size:], axis=1)
            kinds = np.zeros((len(mine), len(names) * k), np.float32)
            for m in range(len(names)):
                kinds[np.arange(len(mine)), m * k + blocks[:, m]] = 1
            for lo in range(0, len(at), 256):
                some = at[lo : lo + 256]
                d2 = None
                for c in x:
                    t = c[some, None] - c
                    t *= t
                    d2 = t if d2 is None else d2 + t
                n = ((d2 <= r * r).astype(np.float32) @ kinds).reshape(len(some), len(names), k)
                for m in range(len(names)):
                    own = blocks[some, m]
                    n[np.arange(len(some)), m, own] = 0
                    ends[m] += np.bincount(own, n[:, m].sum(axis=1, dtype=np.float64), k).astype(np.int64)
                    comm[m] += np.bincount(own, (n[:, m] > 0).sum(axis=1), k).astype(np.int64)

        key, held = None, []
        for b in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in b.columns]
            place = np.stack(cols[:size], axis=1)
            edge = np.nonzero((place[1:] != place[:-1]).any(axis=1))[0] + 1
            for s, e in zip(np.append(0, edge).tolist(), np.append(edge, len(place)).tolist()):
                if s == e:
                    continue
                now = tuple(place[s].tolist())
                if now != key:
                    if held:
                        add(held)
                    key, held = now, []
                held.append([c[s:e] for c in cols[size:]])
        if held:
            add(held)
        yield pa.table({"method": np.repeat(names, k), "block": np.tile(np.arange(k, dtype=np.int32), len(names)), "ends": ends.ravel(), "comm": comm.ravel()}).to_batches()[0]

    found = dealt.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(run, "method string, block int, ends long, comm long")
    return found.groupBy("method", "block").agg(F.sum("ends").alias("ends"), F.sum("comm").alias("comm"))


def boundary_vertices(edges: DataFrame, a: DataFrame) -> DataFrame:
    """Vertices with a neighbour in another block."""
    ends = cut_edges(edges, a).select(F.explode(F.array("src", "dst")).alias("pid"))
    return a.join(ends, "pid", "left_semi")


def interior_vertices(edges: DataFrame, a: DataFrame) -> DataFrame:
    ends = cut_edges(edges, a).select(F.explode(F.array("src", "dst")).alias("pid"))
    return a.join(ends, "pid", "left_anti")


# -- diameters ----------------------------------------------------------------------------------------------------------


def distances(start: int, neighbours: list[np.ndarray]) -> np.ndarray:
    """Hops from start; -1 where unreachable."""
    out = np.full(len(neighbours), -1)
    out[start] = 0
    front = [start]
    while front:
        nxt = []
        for v in front:
            for u in neighbours[v]:
                if out[u] < 0:
                    out[u] = out[v] + 1
                    nxt.append(u)
        front = nxt
    return out


def _lists(t: pa.Table) -> list[np.ndarray]:
    pid = t.column("pid").to_numpy()
    src, dst = (t.column(c).to_numpy(zero_copy_only=False) for c in ("src", "dst"))
    index = {int(v): n for n, v in enumerate(sorted(set(pid.tolist())))}
    out: list[list[int]] = [[] for _ in index]
    for s, d in zip(src.tolist(), dst.tolist()):
        if s == s and d == d and s is not None and d is not None:
            out[index[int(s)]].append(index[int(d)])
    return [np.unique(np.array(x, np.int64)) for x in out]


def exact_diameter(neighbours) -> float:
    most = 0
    for v in range(len(neighbours)):
        d = distances(v, neighbours)
        if (d < 0).any():
            return float("inf")
        most = max(most, int(d.max()))
    return float(most)


def fringe_diameter(neighbours, rounds: int = 3) -> float:
    """Lower bound: from the vertex of most neighbours (lowest id of ties), then eccentricities of the farthest levels."""
    first = max(range(len(neighbours)), key=lambda v: (len(neighbours[v]), -v))
    d = distances(first, neighbours)
    if (d < 0).any():
        return float("inf")
    most = level = int(d.max())
    for _ in range(rounds):
        if level <= 0 or most > 2 * (level - 1):
            break
        for v in np.nonzero(d == level)[0].tolist():
            most = max(most, int(distances(v, neighbours).max()))
        level -= 1
    return float(most)


def block_diameters(edges: DataFrame, a: DataFrame, exact: bool = False, rounds: int = 3, most: int = 5_000_000) -> DataFrame:
    """(block, diam) by breadth-first search inside each block, in one task a block; blocks over `most` vertices are refused."""
    inner = edge_blocks(edges, a).where("b1 = b2")
    both = inner.select(F.col("b1").alias("block"), "src", "dst").unionByName(inner.select(F.col("b1").alias("block"), F.col("dst").alias("src"), F.col("src").alias("dst")))
    rows = a.select("block", "pid").join(both, (a["block"] == both["block"]) & (a["pid"] == both["src"]), "left").select(a["block"], "pid", "src", "dst")

    def run(t: pa.Table) -> pa.Table:
        lists = _lists(t)
        if len(lists) > most:
            raise ValueError(f"a block has {len(lists)} vertices; use block_levels for such")
        value = exact_diameter(lists) if exact else fringe_diameter(lists, rounds)
        return pa.table({"block": pa.array([t.column("block")[0].as_py()], pa.int32()), "diam": pa.array([value])})

    return rows.groupBy("block").applyInArrow(run, "block int, diam double")


def block_levels(edges: DataFrame, a: DataFrame, starts: DataFrame, cap: int | None = None) -> DataFrame:
    """(block, depth): breadth-first depth from one start a block, as frontier joins; for blocks too large for one task.

    Goes on until no vertex is new; with a cap, raises if there are new ones after that many levels.
    """
    from meshcut.sources.scratch import written

    inner = edge_blocks(edges, a).where("b1 = b2").select("src", "dst", "ew")
    both = arcs(inner)
    seen = written(starts.select("block", "pid", F.lit(0).alias("level")), "levels")
    for level in itertools.count():
        front = seen.where(F.col("level") == level)
        nxt = front.join(both, front["pid"] == both["src"]).select("block", F.col("dst").alias("pid")).distinct()
        new = nxt.join(seen, ["block", "pid"], "left_anti").withColumn("level", F.lit(level + 1))
        if not new.limit(1).count():
            break
        if level == cap:
            raise RuntimeError(f"blocks are deeper than {cap} levels; raise cap")
        seen = written(seen.unionByName(new), "levels")
    return seen.groupBy("block").agg(F.max("level").alias("depth"))


def harm_diam(diameters: DataFrame) -> DataFrame:
    return diameters.agg(harmonic_mean(F.col("diam")).alias("harm_diam"))


# -- sparse matrix times vector -------------------------------------------------------------------------------------------


def spmv(both: DataFrame, vec: DataFrame) -> DataFrame:
    """(pid, val): each vertex gets the weighted sum of its neighbours' values."""
    j = both.join(vec.select(F.col("pid").alias("dst"), "val"), "dst")
    return j.groupBy(F.col("src").alias("pid")).agg(F.sum(F.col("ew") * F.col("val")).alias("val"))


def spmv_exchange(edges: DataFrame, a: DataFrame) -> DataFrame:
    """(from_block, to_block, n_values): distinct vertex values a block needs from another for one multiplication."""
    return border(edges, a).groupBy(F.col("block").alias("from_block"), F.col("other").alias("to_block")).agg(F.count("*").alias("n_values"))


def time_spmv(edges: DataFrame, a: DataFrame, vec: DataFrame, repeat: int = 100) -> float:
    """Mean seconds of a multiplication over arcs that lie with the block of their source."""
    both = arcs(edges).join(a.select(F.col("pid").alias("src"), "block"), "src").repartition("block").persist()
    both.count()
    began = time.perf_counter()
    for _ in range(repeat):
        spmv(both, vec).agg(F.sum("val")).first()
    took = time.perf_counter() - began
    both.unpersist()
    return took / repeat


# -- shape, ratios, trends --------------------------------------------------------------------------------------------


def block_aspect(points: DataFrame, a: DataFrame, dims=("x", "y")) -> DataFrame:
    """(block, aspect): longest over shortest side of the bounding box (null if flat)."""
    ext = [(F.max(d) - F.min(d)).alias(f"e_{d}") for d in dims]
    boxes = points.select("pid", *dims).join(a.select("pid", "block"), "pid").groupBy("block").agg(*ext)
    long, short = F.greatest(*(f"e_{d}" for d in dims)), F.least(*(f"e_{d}" for d in dims))
    return boxes.select("block", F.when(short > 0, long / short).alias("aspect"))


def stars(batches, most: int = 1_000_000):
    """Edges (src, dst) as links of each vertex with the least one that they join it with; `most` vertices at once."""
    root: dict[int, int] = {}

    def find(v):
        top = v
        while root[top] != top:
            top = root[top]
        while root[v] != top:
            root[v], v = top, root[v]
        return top

    def links():
        pairs = [(v, find(v)) for v in root]
        pairs = [x for x in pairs if x[0] != x[1]]
        return pa.RecordBatch.from_arrays([pa.array([x[0] for x in pairs], pa.int64()), pa.array([x[1] for x in pairs], pa.int64())], names=["src", "dst"])

    for b in batches:
        for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            root.setdefault(u, u)
            root.setdefault(v, v)
            u, v = find(u), find(v)
            if u != v:
                root[max(u, v)] = min(u, v)
        if len(root) > most:
            yield links()
            root.clear()
    yield links()


def components(edges: DataFrame, a: DataFrame, rounds: int = 200) -> DataFrame:
    """(block, n): connected pieces of each block, by least labels over neighbours and label jumping.

    Each task first joins the edges that it has, so the rounds see a link a vertex and task, not every edge. Of a graph of
    all pairs at most r apart, as radius_edges gives it, no edge is made (`grid_components`).
    """
    if getattr(edges, "_geometric", None):
        return grid_components(*edges._geometric, a, rounds)
    inner = edge_blocks(edges, a).where("b1 = b2").select("src", "dst")
    return labelled(inner, a, rounds).groupBy("block").agg(F.count_distinct("label").alias("n"))


def labelled(inner: DataFrame, a: DataFrame, rounds: int, few: int = 1_000_000) -> DataFrame:
    """(pid, block, label): the vertices of a with the least one that they are joined with by inner (src, dst).

    What the tasks leave of the edges is joined in one task where it is up to `few` links; then two rounds do.
    """
    from meshcut.sources.scratch import written

    inner = written(inner.select("src", "dst").mapInArrow(stars, "src long, dst long"), "links")
    if inner.limit(few + 1).count() <= few:
        inner = inner.coalesce(1).mapInArrow(stars, "src long, dst long")
    inner = written(arcs(inner.withColumn("ew", F.lit(1.0))), "links")
    label = written(a.select("pid", "block", F.col("pid").alias("label")), "labels")
    for _ in range(rounds):
        near = inner.join(label.select(F.col("pid").alias("dst"), "label"), "dst").groupBy(F.col("src").alias("pid")).agg(F.min("label").alias("low"))
        new = label.join(near, "pid", "left").select("pid", "block", F.least("label", F.coalesce("low", "label")).alias("label"), F.col("label").alias("was"))
        jump = new.select(F.col("pid").alias("label"), F.col("label").alias("jump"))
        new = written(new.join(jump, "label").select("pid", "block", F.least("label", "jump").alias("label"), "was"), "labels")
        changed = new.where("label <> was").limit(1).count()
        label = new.select("pid", "block", "label")
        if not changed:
            return label
    raise RuntimeError("components did not settle; raise rounds")


def grid_components(p: DataFrame, r: float, dims, a: DataFrame, rounds: int = 200) -> DataFrame:
    """components() on the graph of all pairs of p at most r apart.

    All points of a block in a grid cell of diagonal r are joined, so the vertices are blocks in cells. Two of them near each
    other are joined if any of their outermost points in some directions are at most r apart; where that leaves it open and
    nothing else joins them, all their points that can be are compared. Points that are not finite are pieces of their own.
    """
    from meshcut.sources.scratch import written

    size = len(dims)
    # a little less, so that no rounding puts points further apart than r into one cell
    side = r / size**0.5 * (1 - 1e-5)
    xs, keys = [f"x{n}" for n in range(size)], [f"k{n}" for n in range(size)]
    points = a.select("pid", "block").join(p.select("pid", *(F.col(d).cast("double").alias(x) for d, x in zip(dims, xs))), "pid", "left")
    finite = reduce(lambda s, x: s & F.coalesce(F.abs(F.col(x)) < float("inf"), F.lit(False)), xs, F.lit(True))
    points = written(points.select("block", *xs, finite.alias("finite")), "points")
    alone = points.where("not finite").groupBy("block").agg(F.count("*").alias("n"))
    points = points.where("finite").select("block", *xs, *(F.floor(F.col(x) / side).cast("long").alias(k) for x, k in zip(xs, keys)))

    at = F.struct(*xs)
    ways = [w for w in itertools.product((-1, 0, 1), repeat=size) if w > (0,) * size]
    along = [reduce(lambda s, t: s + t, [F.col(x) * c for x, c in zip(xs, w) if c]) for w in ways]
    ends = F.array(*(f(at, v) for v in along for f in (F.min_by, F.max_by)))
    box = [f(x).alias(f"{z}_{x}") for x in xs for z, f in (("lo", F.min), ("hi", F.max))]
    nodes = points.groupBy("block", *keys).agg(F.count("*").alias("n"), F.array_distinct(ends).alias("ends"), *box)
    nodes = written(nodes.withColumn("pid", F.monotonically_increasing_id()), "nodes")

    reach = 1 + int(r / side)
    offsets = [w for w in itertools.product(range(-reach, reach + 1), repeat=size) if w > (0,) * size and sum(max(abs(c) - 1, 0) ** 2 for c in w) * side**2 <= r * r]
    places = F.array(*(F.struct(*((F.col(k) + c).alias(k) for k, c in zip(keys, w))) for w in offsets))
    facts = ["n", "ends", *(f"{z}_{x}" for x in xs for z in ("lo", "hi"))]
    one = nodes.select("block", F.col("pid").alias("src"), *(F.col(c).alias(f"u_{c}") for c in facts), F.inline(places))
    two = nodes.select("block", *keys, F.col("pid").alias("dst"), *(F.col(c).alias(f"v_{c}") for c in facts))
    square = lambda parts: reduce(lambda s, t: s + t, [t * t for t in parts])
    gap = square([F.greatest(F.lit(0.0), F.col(f"v_lo_{x}") - F.col(f"u_hi_{x}"), F.col(f"u_lo_{x}") - F.col(f"v_hi_{x}")) for x in xs])
    near = F.exists("u_ends", lambda s: F.exists("v_ends", lambda t: square([s[x] - t[x] for x in xs]) <= r * r))
    pairs = one.join(two, ["block", *keys]).where(gap <= r * r * (1 + 1e-9)).withColumn("near", near)
    # of up to two points all are outermost ones
    pairs = written(pairs.where("near or u_n > 2 or v_n > 2").select("src", "dst", "near", *(f"{s}_{z}_{x}" for s in "uv" for z in ("lo", "hi") for x in xs)), "pairs")
    links = pairs.where("near").select("src", "dst")
    label = labelled(links, nodes, rounds)

    of = label.select("pid", "label")
    open_ = pairs.where("not near").join(of.select(F.col("pid").alias("src"), F.col("label").alias("l1")), "src").join(of.select(F.col("pid").alias("dst"), F.col("label").alias("l2")), "dst")
    open_ = written(open_.where("l1 <> l2").drop("l1", "l2", "near"), "open")
    if open_.limit(1).count():
        own = points.join(nodes.select("block", *keys, "pid"), ["block", *keys]).select("pid", *xs)

        def side_points(mine, other, number):
            away = square([F.greatest(F.lit(0.0), F.col(f"{other}_lo_{x}") - F.col(x), F.col(x) - F.col(f"{other}_hi_{x}")) for x in xs])
            key = "src" if mine == "u" else "dst"
            return own.join(open_.withColumnRenamed(key, "pid").withColumn(key, F.col("pid")), "pid").where(away <= r * r * (1 + 1e-9)).select("src", "dst", F.lit(number).alias("side"), *xs)

        both = side_points("u", "v", 0).unionByName(side_points("v", "u", 1))
        met = both.repartition("src", "dst").sortWithinPartitions("src", "dst", "side").mapInArrow(meeting(r, size), "src long, dst long")
        label = labelled(links.unionByName(written(met, "met")), nodes, rounds)
    pieces = label.groupBy("block").agg(F.count_distinct("label").alias("n"))
    return pieces.unionByName(alone).groupBy("block").agg(F.sum("n").alias("n"))


def meeting(r: float, size: int, most: int = 1 << 20):
    """Rows by src, dst, side (0, 1) with coordinates: those (src, dst) that have points of both sides at most r apart."""

    def run(batches):
        key, first, met = None, [], False
        for b in batches:
            src, dst, side, *xs = (c.to_numpy(zero_copy_only=False) for c in b.columns)
            edge = np.nonzero((src[1:] != src[:-1]) | (dst[1:] != dst[:-1]) | (side[1:] != side[:-1]))[0] + 1
            found = []
            for s, e in zip(np.append(0, edge).tolist(), np.append(edge, len(src)).tolist()):
                if s == e:
                    continue
                if (src[s], dst[s]) != key:
                    key, first, met = (src[s], dst[s]), [], False
                here = [x[s:e] for x in xs]
                if side[s] == 0:
                    first.append(here)
                elif first and not met:
                    if len(first) > 1:
                        first = [[np.concatenate(c) for c in zip(*first)]]
                    step = max(1, most // len(first[0][0]))
                    for lo in range(0, e - s, step):
                        d2 = sum((u[:, None] - v[None, lo : lo + step]) ** 2 for u, v in zip(first[0], here))
                        if (d2 <= r * r).any():
                            met = True
                            found.append(key)
                            break
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found)], names=["src", "dst"])

    return run


def ratio_table(report: DataFrame, base: str, measures: list[str]) -> DataFrame:
    """(class, method, measure ratios): geometric mean over graphs of each measure relative to the base method's."""
    own = report.where(F.col("method") != base)
    ref = report.where(F.col("method") == base).select("graph", *(F.col(m).alias(f"_{m}") for m in measures))
    return own.join(ref, "graph").groupBy("class", "method").agg(*(F.round(geometric_mean(F.col(m) / F.col(f"_{m}")), 6).alias(m) for m in measures))


def fit_trend(rows: DataFrame) -> DataFrame:
    """(method, a, b) of t = 2**b * n**a, least squares on binary logarithms."""
    x, y = F.log2(F.col("n").cast("double")), F.log2("seconds")
    return rows.groupBy("method").agg(F.round(F.regr_slope(y, x), 6).alias("a"), F.round(F.regr_intercept(y, x), 6).alias("b"))


def strong_efficiency(rows: DataFrame) -> DataFrame:
    """(method, p, efficiency): speedup over the least p, per process."""
    w = Window.partitionBy("method").orderBy("p")
    first_s, first_p = F.first_value("seconds").over(w), F.first_value("p").over(w)
    return rows.select("method", "p", F.round(first_s * first_p / (F.col("seconds") * F.col("p")), 6).alias("efficiency"))


def weak_growth(rows: DataFrame) -> DataFrame:
    """(method, p, growth): seconds over those at half the processes."""
    w = Window.partitionBy("method").orderBy("p")
    return rows.select("method", "p", F.round(F.col("seconds") / F.lag("seconds").over(w), 6).alias("growth"))
