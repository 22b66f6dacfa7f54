"""Thin operators around the methods: scaling, box and range filters, as-of, interval and salted joins, quantiles."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from meshcut.sources.scratch import written


def scale(p: DataFrame, dims, how: str = "range") -> DataFrame:
    """'range': to 0..1 over the bounding box; 'std': mean 0, deviation 1; 'none'. Flat axes become 0."""
    if how == "none":
        return p
    one = [F.min(d).alias(f"_a{d}") if how == "range" else F.avg(d).alias(f"_a{d}") for d in dims]
    two = [(F.max(d) - F.min(d)).alias(f"_s{d}") if how == "range" else F.stddev_pop(d).alias(f"_s{d}") for d in dims]
    box = p.agg(*one, *two)  # one row
    out = p.crossJoin(F.broadcast(box))
    return out.withColumns({d: F.when(F.col(f"_s{d}") > 0, (F.col(d) - F.col(f"_a{d}")) / F.col(f"_s{d}")).otherwise(0.0) for d in dims}).drop(*box.columns)


def in_box(p: DataFrame, box: dict[str, tuple]) -> DataFrame:
    return p.where(reduce(lambda a, b: a & b, [F.col(d).between(lo, hi) for d, (lo, hi) in box.items()]))


def within(p: DataFrame, centre: dict[str, float], r: float) -> DataFrame:
    d2 = reduce(lambda a, b: a + b, [(F.col(d) - c) * (F.col(d) - c) for d, c in centre.items()])
    return p.where(d2 <= r * r)


def curve_ranges(xs: tuple[int, int], ys: tuple[int, int], bits: int, most: int = 64) -> list[tuple[int, int]]:
    """Hilbert key ranges [lo, hi) that cover a box of cells: squares of the curve's hierarchy, split until `most` ranges."""

    def key(x: int, y: int) -> int:
        out, top = 0, (1 << bits) - 1
        for b in range(bits - 1, -1, -1):
            rx, ry = x >> b & 1, y >> b & 1
            out = out * 4 + (3 * rx ^ ry)
            if not ry:
                x, y = (top - y, top - x) if rx else (y, x)
        return out

    done, open_ = [], [(0, 0, bits)]
    while open_:
        x, y, b = open_.pop(0)
        side = 1 << b
        if x > xs[1] or y > ys[1] or x + side - 1 < xs[0] or y + side - 1 < ys[0]:
            continue
        inside = x >= xs[0] and y >= ys[0] and x + side - 1 <= xs[1] and y + side - 1 <= ys[1]
        if inside or not b or len(done) + len(open_) >= most:
            lo = key(x, y) >> 2 * b << 2 * b
            done.append((lo, lo + (1 << 2 * b)))
        else:
            open_ += [(x + i * side // 2, y + j * side // 2, b - 1) for i in (0, 1) for j in (0, 1)]
    merged: list[tuple[int, int]] = []
    for lo, hi in sorted(done):
        if merged and merged[-1][1] >= lo:
            merged[-1] = (merged[-1][0], max(hi, merged[-1][1]))
        else:
            merged.append((lo, hi))
    return merged


def in_ranges(p: DataFrame, key: str, ranges: list[tuple[int, int]]) -> DataFrame:
    """Rows whose key is in one of the ranges; on sorted files the reader skips row groups outside them."""
    return p.where(reduce(lambda a, b: a | b, [(F.col(key) >= lo) & (F.col(key) < hi) for lo, hi in ranges], F.lit(False)))


def collapse(p: DataFrame, dims) -> DataFrame:
    """Points at one place as one point of their weight."""
    return p.groupBy(*dims).agg(F.sum("w").alias("w"), F.min("pid").alias("pid")).select("pid", *dims, "w")


def as_of(left: DataFrame, right: DataFrame, t: str, values: list[str], by: list[str] | None = None, slack: float | None = None) -> DataFrame:
    """left with the values of the latest right row at or before t (within `by`, or within coarse time buckets).

    Without `by`, each right row gets the next one's t from its neighbour in a range-partitioned sort (the last of a
    partition from the partitions after it, of which there is one row each), and rows meet in buckets of t; no window runs
    over all rows.
    """
    by = by or []
    if by:
        r = right.select(*by, t, F.lit(0).alias("_side"), F.struct(*values).alias("_v"))
        both = left.withColumn("_side", F.lit(1)).unionByName(r, allowMissingColumns=True)
        w = Window.partitionBy(*by).orderBy(t, "_side").rowsBetween(Window.unboundedPreceding, 0)
        out = both.withColumn("_v", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
        return out.select(*left.columns, *(F.col(f"_v.{v}").alias(v) for v in values))
    ends = with_next(right.select(t, *values), t).withColumnRenamed(t, "_from")
    span = left.agg(F.min(t).alias("lo"), F.max(t).alias("hi")).first()
    width = slack or max((span["hi"] - span["lo"]) / 1000, 1e-9)
    hit = interval_join(left.select(*left.columns), ends.withColumn("_to", F.coalesce("_to", F.lit(span["hi"] + width))), t, "_from", "_to", width, how="left")
    return hit.select(*left.columns, *values)


def with_next(df: DataFrame, t: str) -> DataFrame:
    """df with `_to`, the next row's t in the order of t (null for the last); rows of equal t follow one another."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = written(df.repartitionByRange(parts, t).withColumn("_part", F.spark_partition_id()), "by-time")
    firsts = dealt.groupBy("_part").agg(F.min(t).alias("_first"))
    after = firsts.select("_part", F.lead("_first").over(Window.orderBy("_part")).alias("_after"))  # a row a partition
    out = dealt.withColumn("_to", F.lead(t).over(Window.partitionBy("_part").orderBy(t)))
    return out.join(F.broadcast(after), "_part").withColumn("_to", F.coalesce("_to", "_after")).drop("_part", "_after")


def interval_join(left: DataFrame, right: DataFrame, t: str, lo: str, hi: str, width: float, how: str = "inner") -> DataFrame:
    """Rows of left whose t is in [lo, hi) of a row of right: both meet in buckets of `width`, an equi join and a range test."""
    l = left.withColumn("_k", F.floor(F.col(t) / width))
    r = right.withColumn("_k", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return l.join(r, (l["_k"] == r["_k"]) & (F.col(t) >= F.col(lo)) & (F.col(t) < F.col(hi)), how).drop("_k")


def near_counts(p: DataFrame, group: Column, t: str, reach: float = 1.0) -> DataFrame:
    """(pid, near): rows of the same group whose t is at most `reach` before or after (of a null t: those of null t).

    Rows meet in intervals of t, each also in those next to its own; a sorted interval answers each of its rows with two
    searches, so neither a row nor a task reads a whole frame or group.
    """
    none, odd = F.lit(-(2**63)), F.lit(1 - 2**63)  # keys of null and of NaN
    rows = p.select("pid", F.coalesce(group.cast("long"), none).alias("g"), F.col(t).cast("double").alias("t"))
    # a little over the reach: t - reach and t + reach are rounded
    slack = reach * (1 + 1e-9)
    own = F.when(F.col("t").isNull(), none).when(F.isnan("t"), odd).otherwise(F.floor(F.col("t") / reach))
    around = F.sequence(F.floor((F.col("t") - slack) / reach), F.floor((F.col("t") + slack) / reach))
    dealt = rows.select("pid", "g", "t", F.explode(F.when(F.col("t").isNull() | F.isnan("t"), F.array(own)).otherwise(around)).alias("k"), own.alias("own"))
    dealt = dealt.select("g", "k", "t", F.when(F.col("k") == F.col("own"), F.col("pid")).alias("pid"), (F.col("k") == F.col("own")).alias("mine"))

    def count(batches):
        key, held = None, []

        def answer():
            x, pid, mine = (np.concatenate(c) for c in zip(*held))
            ask = x[mine]
            if np.isnan(ask).all():
                n = np.full(len(ask), len(x))
            else:
                n = np.searchsorted(x, ask + reach, "right") - np.searchsorted(x, ask - reach, "left")
            return pa.RecordBatch.from_arrays([pa.array(pid[mine], pa.int64()), pa.array(n, pa.int64())], names=["pid", "near"])

        for b in batches:
            g, k, x, pid, mine = (b.column(c) for c in range(5))
            g, k, x, mine = (c.to_numpy(zero_copy_only=False) for c in (g, k, x, mine))
            pid = pid.fill_null(0).to_numpy(zero_copy_only=False)
            edge = np.nonzero((g[1:] != g[:-1]) | (k[1:] != k[:-1]))[0] + 1
            for s, e in zip(np.append(0, edge).tolist(), np.append(edge, len(g)).tolist()):
                now = int(g[s]), int(k[s])
                if now != key:
                    if held:
                        yield answer()
                    key, held = now, []
                held.append((x[s:e], pid[s:e], mine[s:e]))
        if held:
            yield answer()

    return dealt.repartition("g", "k").sortWithinPartitions("g", "k", "t").mapInArrow(count, "pid long, near long")


def migration(old: DataFrame, new: DataFrame, p: DataFrame) -> DataFrame:
    """(was, now, n, w): points and weight that go from block to block; null where a point is in one assignment only."""
    both = old.select("pid", F.col("block").alias("was")).join(new.select("pid", F.col("block").alias("now")), "pid", "full")
    return both.join(p.select("pid", "w"), "pid").groupBy("was", "now").agg(F.count("*").alias("n"), F.sum("w").alias("w"))


def two_hop(edges: DataFrame) -> DataFrame:
    """Pairs src < dst joined by a path of two edges."""
    a = edges.select("src", "dst").union(edges.select("dst", "src"))
    b = a.toDF("_mid", "_end")
    return a.join(b, a["dst"] == b["_mid"]).where("src < _end").select("src", F.col("_end").alias("dst")).distinct()


def salted_join(left: DataFrame, right: DataFrame, on: str, salt: int) -> DataFrame:
    """Equi join whose hot keys are spread over `salt` tasks: left rows draw a salt, right rows are repeated for each."""
    l = left.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salt)))
    r = right.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salt - 1).cast("long"))))
    return l.join(r, [on, "_salt"]).drop("_salt")


def histogram_quantile(p: DataFrame, col: str, q: float, bins: int = 1024) -> float:
    """The least value with at least a share q of the rows at or below it, by refining the bin that holds it."""
    lo, hi, n = p.agg(F.min(col), F.max(col), F.count("*")).first()
    goal, before = q * n, 0
    while True:
        part = p.where((F.col(col) >= lo) & (F.col(col) <= hi))
        count = part.count()
        if count <= 10_000 or hi <= lo:
            # at most 10 000 values, or one
            values = sorted(r[0] for r in part.select(col).limit(10_001).collect()) if hi > lo else [lo]
            k = min(len(values) - 1, max(0, -int(-(goal - before) // 1) - 1))
            return values[k] if hi > lo else lo
        step = (hi - lo) / bins
        b = F.least(F.lit(bins - 1), F.floor((F.col(col) - lo) / step))
        for r in part.groupBy(b.alias("b")).agg(F.count("*").alias("n"), F.min(col).alias("lo"), F.max(col).alias("hi")).orderBy("b").collect():
            if before + r["n"] >= goal:
                lo, hi = r["lo"], r["hi"]
                break
            before += r["n"]
