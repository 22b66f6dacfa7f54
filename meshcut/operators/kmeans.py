"""Balanced k-means: rebalancing assignment under per-block influence, weighted centre moves, influence erosion.

Points stay where they are; a pass over them is one narrow map and one aggregation of k rows (weight, moments, box and
counters of every block), the only thing that reaches the driver. Centres and influence live on the driver and go to the
tasks as literals or closure values. Two engines give the same blocks (ties: lowest block):

* expr: a fold over the literal centres inside code generation; with bounds it carries, for a written generation of the
  assignment, the best and second-best distance, relaxed lazily by per-block pairs, and re-evaluates only unsure points;
* tile: an Arrow map over runs of curve-sorted points, each with its bounding box: only centres that can be best or second
  best for some point of the box are evaluated.
"""

from __future__ import annotations

import json
import math
import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from meshcut.functions.geometry import centre_array, two_nearest
from meshcut.operators import ranks
from meshcut.sources.scratch import discard, written


@dataclass
class Centre:
    block: int
    at: tuple[float, ...]
    influence: float = 1.0


@dataclass
class Centres:
    rows: list[Centre]

    @classmethod
    def initial(cls, seeds: DataFrame, dims) -> Centres:
        return cls([Centre(r["block"], tuple(float(r[d]) for d in dims)) for r in sorted(seeds.collect(), key=lambda r: r["block"])])

    def moved(self, at=None, influence=None) -> Centres:
        return Centres([Centre(c.block, at[n] if at else c.at, influence[n] if influence else c.influence) for n, c in enumerate(self.rows)])


@dataclass
class Partition:
    assignment: DataFrame
    centres: Centres
    balanced: bool
    imbalance: float
    rounds: int
    passes: int
    converged: bool
    too_heavy: bool
    counters: dict = field(default_factory=dict)


# -- k-sized steps: the same rules as Column expressions and on the driver ---------------------------------------------


def influence_factor(target, size, d: int, cap: float | None = 0.05):
    """What an influence is multiplied by: (target / size)**(1/d), within 1 ± cap. Oversized blocks lose influence."""
    if size <= 0:
        return 1 + cap if cap is not None else 2.0
    f = (target / size) ** (1 / d)
    return f if cap is None else min(max(f, 1 - cap), 1 + cap)


def influence_factor_column(target: Column, size: Column, d: int, cap: float | None = 0.05) -> Column:
    ratio = F.try_divide(target, size)
    f = F.sqrt(ratio) if d == 2 else F.cbrt(ratio) if d == 3 else F.pow(ratio, F.lit(1 / d))
    if cap is None:
        return F.coalesce(f, F.lit(2.0))
    return F.coalesce(F.greatest(F.least(f, F.lit(1 + cap)), F.lit(1 - cap)), F.lit(1 + cap))


def erosion_share(shift: float, beta: float) -> float:
    """alpha: how far influence goes back to 1, a logistic curve of the shift over beta from 0."""
    if beta <= 0:
        return 1.0 if shift > 0 else 0.0
    return 2 / (1 + math.exp(-shift / beta)) - 1


def eroded(influence: float, shift: float, beta: float) -> float:
    return math.exp((1 - erosion_share(shift, beta)) * math.log(influence))


def eroded_column(influence: Column, shift: Column, beta: Column) -> Column:
    alpha = F.when(beta > 0, 2 / (1 + F.exp(-shift / beta)) - 1).otherwise(F.when(shift > 0, 1.0).otherwise(0.0))
    return F.exp((1 - alpha) * F.log(influence))


def imbalance(sizes: list[float], targets: list[float]) -> float:
    return max((s / t for s, t in zip(sizes, targets) if t > 0), default=0.0) - 1


# -- one pass over the points -------------------------------------------------------------------------------------------


def assign(points: DataFrame, centres: Centres, dims, old: Bounds | None = None) -> DataFrame:
    """points with block, eff, eff2 and skipped; old: bounds of an earlier generation in columns block, eff, eff2."""
    xs = [F.col(d) for d in dims]
    best = two_nearest(xs, centre_array(centres))
    if old is None:
        return points.withColumn("_a", best).select(*points.columns, "_a.block", "_a.eff", "_a.eff2", F.lit(0).alias("skipped"))
    keep = [c for c in points.columns if c not in ("block", "eff", "eff2", "skipped")]
    r, s = (F.get(F.array(*map(F.lit, x)), F.col("block")) for x in (old.r, old.s))
    upper, lower = r * F.col("eff") + s, old.rho * F.col("eff2") - old.sigma
    held = points.withColumns({"_up": upper, "_low": lower})
    kept = F.struct("block", F.col("_up").alias("eff"), F.col("_low").alias("eff2"))
    return held.withColumn("_a", F.when(F.col("_up") < F.col("_low"), kept).otherwise(best)).select(*keep, "_a.block", "_a.eff", "_a.eff2", (F.col("_up") < F.col("_low")).cast("int").alias("skipped"))


@dataclass
class Bounds:
    """Lazy relaxation since a generation: upper = r*u + s per block, lower = rho*l - sigma."""

    r: list[float]
    s: list[float]
    rho: float = 1.0
    sigma: float = 0.0

    @classmethod
    def fresh(cls, k: int) -> Bounds:
        return cls([1.0] * k, [0.0] * k)

    def relax(self, old: Centres, new: Centres) -> None:
        """After influence changed or centres moved: effective distances change by the influence ratio, then by the shift."""
        ratio = [a.influence / b.influence for a, b in zip(old.rows, new.rows)]
        drift = [math.dist(a.at, b.at) / b.influence for a, b in zip(old.rows, new.rows)]
        self.r = [r * q for r, q in zip(self.r, ratio)]
        self.s = [s * q + d for s, q, d in zip(self.s, ratio, drift)]
        low = min(ratio)
        self.rho, self.sigma = self.rho * low, self.sigma * low + max(drift)


def block_stats(assigned: DataFrame, dims, weight: str = "w") -> DataFrame:
    """One row a block: n, weight, weighted sums, box, skipped."""
    w = F.col(weight).cast("double")
    aggs = [F.count("*").alias("n"), F.sum(w).alias("weight"), F.sum("skipped").alias("skipped")]
    for d in dims:
        aggs += [F.sum(w * F.col(d)).alias(f"s_{d}"), F.min(d).alias(f"lo_{d}"), F.max(d).alias(f"hi_{d}")]
    return assigned.groupBy("block").agg(*aggs)


def nearest_of_run(x: np.ndarray, at: np.ndarray, influence: np.ndarray):
    """(best, eff, eff2, centres evaluated) of points x under the centres that their bounding box leaves."""
    lo, hi = x.min(axis=0), x.max(axis=0)
    gap = np.maximum(0, np.maximum(lo - at, at - hi))
    far = np.maximum(np.abs(at - lo), np.abs(at - hi))
    least = np.sqrt((gap * gap).sum(axis=1)) / influence
    most = np.sqrt((far * far).sum(axis=1)) / influence
    # some two centres are within the second-least of the largest distances everywhere in the box
    limit = np.partition(most, 1)[1] if len(most) > 1 else most[0]
    use = np.nonzero(least <= limit * (1 + 1e-12))[0]
    d2 = np.zeros((len(x), len(use)))
    for c in range(x.shape[1]):
        diff = x[:, c, None] - at[None, use, c]
        d2 += diff * diff
    e = np.sqrt(d2) / influence[None, use]
    best = e.argmin(axis=1)
    rows = np.arange(len(x))
    eff = e[rows, best]
    if len(use) > 1:
        e[rows, best] = np.inf
        eff2 = e.min(axis=1)
    else:
        eff2 = np.full(len(x), np.inf)
    return use[best], eff, eff2, len(use)


def tile_map(centres: Centres, dims, weight: str, run_length: int, stats: bool):
    at = np.array([c.at for c in centres.rows], float)
    influence = np.array([c.influence for c in centres.rows], float)
    k, d = at.shape

    def run(batches):
        sums = np.zeros((k, 3 + d))
        lo, hi = np.full((k, d), np.inf), np.full((k, d), -np.inf)
        for b in batches:
            x = np.stack([b.column(b.schema.get_field_index(c)).to_numpy(zero_copy_only=False).astype(float) for c in dims], axis=1)
            w = b.column(b.schema.get_field_index(weight)).to_numpy(zero_copy_only=False).astype(float) if weight else np.ones(len(x))
            block, eff, eff2 = np.zeros(len(x), np.int64), np.zeros(len(x)), np.zeros(len(x))
            evaluated = 0
            for s in range(0, len(x), run_length):
                e = min(s + run_length, len(x))
                block[s:e], eff[s:e], eff2[s:e], c = nearest_of_run(x[s:e], at, influence)
                evaluated += c * (e - s)
            if not stats:
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(block.astype(np.int32)), pa.array(eff), pa.array(eff2), pa.array(np.zeros(len(x), np.int32))], names=[f.name for f in b.schema] + ["block", "eff", "eff2", "skipped"])
                continue
            sums[:, 0] += np.bincount(block, minlength=k)
            sums[:, 1] += np.bincount(block, weights=w, minlength=k)
            if len(x):
                sums[block[0], 2] += evaluated
            for c in range(d):
                sums[:, 3 + c] += np.bincount(block, weights=w * x[:, c], minlength=k)
                np.minimum.at(lo[:, c], block, x[:, c])
                np.maximum.at(hi[:, c], block, x[:, c])
        if stats:
            some = np.nonzero(sums[:, 0])[0]
            columns = [some.astype(np.int32), sums[some, 0].astype(np.int64), sums[some, 1], sums[some, 2], *(z for c in range(d) for z in (sums[some, 3 + c], lo[some, c], hi[some, c]))]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["block", "n", "weight", "evaluated", *(f"{z}_{c}" for c in dims for z in ("s", "lo", "hi"))])

    return run


def assign_tiles(points: DataFrame, centres: Centres, dims, run_length: int = 256) -> DataFrame:
    """As assign, by the tile engine."""
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in points.schema) + ", block int, eff double, eff2 double, skipped int"
    return points.mapInArrow(tile_map(centres, dims, "", run_length, False), schema)


def pass_stats(points: DataFrame, centres: Centres, dims, weight: str, engine: str, bounds: Bounds | None, generation: DataFrame | None, run_length: int = 256):
    """Per block: n, weight, weighted sums and box; and the counters of the pass."""
    k = len(centres.rows)
    if engine == "tile":
        schema = "block int, n long, weight double, evaluated double, " + ", ".join(f"{z}_{c} double" for c in dims for z in ("s", "lo", "hi"))
        part = points.mapInArrow(tile_map(centres, dims, weight, run_length, True), schema)
        rows = part.groupBy("block").agg(*(F.sum(c).alias(c) for c in ("n", "weight", "evaluated", *(f"s_{d}" for d in dims))), *(F.min(f"lo_{d}").alias(f"lo_{d}") for d in dims), *(F.max(f"hi_{d}").alias(f"hi_{d}") for d in dims)).collect()
        counters = {"evaluated": sum(r["evaluated"] for r in rows), "skipped": 0}
    else:
        source = points if generation is None else generation
        rows = block_stats(assign(source, centres, dims, None if generation is None else bounds), dims, weight).collect()
        skipped = sum(r["skipped"] for r in rows)
        counters = {"skipped": skipped, "evaluated": (sum(r["n"] for r in rows) - skipped) * k}
    counters["points"] = sum(r["n"] for r in rows)
    return {r["block"]: r for r in rows}, counters


def box_diagonals(stats: dict, dims) -> float:
    all_ = [math.sqrt(sum((r[f"hi_{d}"] - r[f"lo_{d}"]) ** 2 for d in dims)) for r in stats.values()]
    return sum(all_) / len(all_) if all_ else 0.0


def centre_gap(centres: Centres) -> float:
    at = np.array([c.at for c in centres.rows])
    if len(at) < 2:
        return 0.0
    gaps = [np.sort(np.sqrt(((at - a) ** 2).sum(axis=1)))[1] for a in at]
    return float(np.mean(gaps))


#: Odd multiplier that spreads neighbouring ids over 32 bits.
SPREAD = 2654435761


def in_sample(size: float, n: int) -> Column:
    """Rows whose portable hash falls in the first size / n of its range; larger samples hold smaller ones.

    The id is folded to 32 bits first and multiplied in two halves of 16, so that no product leaves the range of a long.
    """
    low = F.pmod(F.col("pid").bitwiseXOR(F.shiftright("pid", 32)), F.lit(2**32))
    high, rest = F.shiftright(low, 16), F.pmod(low, F.lit(2**16))
    mixed = F.pmod(F.pmod(high * SPREAD, F.lit(2**16)) * 2**16 + rest * SPREAD, F.lit(2**32))
    return mixed < math.ceil(size / max(1, n) * 2**32)


def sample_sizes(n: int, k: int, start: int = 100) -> list[int]:
    """100 points a block, doubled each round, while smaller than the whole set."""
    out, size = [], start * k
    while size < n:
        out.append(size)
        size *= 2
    return out


def balanced_kmeans(points: DataFrame, k: int, *, eps: float = 0.03, dims=("x", "y"), weight: str = "w", target: list[float] | None = None, max_iter: int = 50, max_balance: int = 20, cap: float | None = 0.05, threshold: float = 0.005, beta: str = "bbox", erosion: bool = True, bounds: bool = True, sample_start: int | None = 100, seed: str = "sfc", engine: str = "auto", stop: str = "both", balance: bool = True, limit: str = "avg", resume: str | None = None, digits: int | None = None, curve_dims=None, start: Centres | None = None) -> Partition:
    """Splits points (pid, dims, weight) into k blocks of equal weight (or of the shares in target) and small spread.

    threshold is relative to beta, the mean block diameter ('bbox': box diagonals, 'centre_gap': nearest centres). stop:
    'both' ends when centres rest and blocks balance, 'balance' at the first balanced result. balance=False is plain
    k-means. The best balanced iterate seen is returned; `balanced` tells whether there was one, `too_heavy` whether a
    single point outweighs a block's limit, so none can exist. resume: a folder to keep the centres of each round in.
    start: centres of an earlier partition, in place of seeds. curve_dims: two or three dimensions for the curve sort, where dims has more.
    digits: centres and influences are rounded to so many places in every step, so that the result does not hang on the
    order in which sums are taken. counters has the seconds of the curve sort, the seeds and the rounds.
    """
    spark = points.sparkSession
    dims = list(dims)
    exact = (lambda v: v) if digits is None else (lambda v: round(v, digits))
    clock = [time.perf_counter()]
    engine = engine if engine != "auto" else "expr" if k <= 16 else "tile"
    data = written(ranks.spatial_sort(points.select("pid", *dims, weight), list(curve_dims or dims)), "points")
    n, whole, heaviest = data.agg(F.count("*"), F.sum(F.col(weight).cast("double")), F.max(weight)).first()
    clock.append(time.perf_counter())
    shares = target or [1 / k] * k
    if not n:
        empty = data.select("pid", F.lit(0).alias("block"))
        return Partition(empty, Centres([]), True, 0.0, 0, 0, True, False)
    k_real = min(k, n)
    seeds = None if start else ranks.random_seeds(data, k_real, dims) if seed == "random" else ranks.sfc_seeds(data, k_real, dims, "weight" if seed == "weight" else "rank")
    first = start or Centres.initial(seeds, dims)
    centres = start or Centres([Centre(b, first.rows[b % len(first.rows)].at) for b in range(k)])
    clock.append(time.perf_counter())
    first_round = 0
    if resume:
        try:
            kept = json.loads(spark.read.text(resume).first()[0])
            centres, first_round = Centres([Centre(b, tuple(a), i) for b, a, i in kept["centres"]]), kept["round"]
        except Exception as e:
            if "PATH_NOT_FOUND" not in str(e):
                raise
    sizes = sample_sizes(n, k, sample_start) if sample_start else []
    total = {"skipped": 0, "evaluated": 0, "points": 0}
    best: tuple[float, Centres] | None = None
    passes, converged, last_imbalance = 0, False, math.inf
    generation, lazy = None, None
    factor = 1.0 if limit == "avg" else math.ceil(whole / k) / (whole / k)
    round_no = first_round
    for round_no in range(first_round, max_iter + len(sizes)):
        sampled = round_no < len(sizes)
        rows = data.where(in_sample(sizes[round_no], n)) if sampled else data
        for turn in range(max_balance if balance else 1):
            use = bounds and not sampled and engine == "expr"
            if use and generation is None:
                generation, lazy = written(assign(data, centres, dims), "generation"), Bounds.fresh(k)
            stats, counters = pass_stats(rows, centres, dims, weight, engine, lazy, generation if use else None)
            passes += 1
            for key in total:
                total[key] += counters[key]
            if use and counters["skipped"] < 0.5 * counters["points"]:
                discard(generation)
                generation = None
            mass = sum(r["weight"] for r in stats.values())
            loads = [stats[b]["weight"] if b in stats else 0.0 for b in range(k)]
            goals = [f * mass * factor for f in shares]
            last_imbalance = imbalance(loads, goals)
            met = last_imbalance <= eps
            if met or not balance or turn == max_balance - 1:
                break
            new = centres.moved(influence=[exact(c.influence * influence_factor(g, s, len(dims), cap)) for c, g, s in zip(centres.rows, goals, loads)])
            if lazy is not None:
                lazy.relax(centres, new)
            centres = new
        if met and not sampled and (best is None or last_imbalance <= best[0]):
            best = (last_imbalance, centres)
        width = box_diagonals(stats, dims) if beta == "bbox" else centre_gap(centres)
        means = [tuple(exact(stats[b][f"s_{d}"] / stats[b]["weight"]) for d in dims) if b in stats else centres.rows[b].at for b in range(k)]
        shifts = [math.dist(a, c.at) for a, c in zip(means, centres.rows)]
        resting = max(shifts) < threshold * width or max(shifts) == 0
        if not sampled and met and (resting or stop == "balance"):
            converged, best = resting, (last_imbalance, centres)
            break
        if not sampled and resting and not balance:
            converged = True
            break
        influence = [exact(eroded(c.influence, s, width)) for c, s in zip(centres.rows, shifts)] if erosion and balance else None
        new = centres.moved(at=means, influence=influence)
        if lazy is not None:
            lazy.relax(centres, new)
        centres = new
        if resume:
            state = json.dumps({"round": round_no + 1, "centres": [[c.block, list(c.at), c.influence] for c in centres.rows]})
            spark.createDataFrame([(state,)], "value string").coalesce(1).write.mode("overwrite").text(resume)
    if best is not None and balance:
        last_imbalance, centres = best
    result = assign_tiles(data, centres, dims) if engine == "tile" else assign(data, centres, dims)
    clock.append(time.perf_counter())
    seconds = {f"seconds_{what}": b - a for what, a, b in zip(("index", "seeds", "rounds"), clock, clock[1:])}
    counters = total | {"skip_rate": total["skipped"] / max(1, total["points"]), "centres_per_point": total["evaluated"] / max(1, total["points"] - total["skipped"])} | seconds
    return Partition(result.select("pid", "block", "eff", "eff2"), centres, best is not None if balance else last_imbalance <= eps, last_imbalance, round_no + 1, passes, converged, bool(heaviest > (1 + eps) * whole * max(shares)), counters)


def sse(assigned: DataFrame, centres: Centres, dims) -> DataFrame:
    """Sum of squared distances of the points to their blocks' centres, in one row."""
    at = centre_array(centres)
    own = F.get(at, F.col("block"))
    part = None
    for c, d in enumerate(dims):
        x = (F.col(d) - own[f"c{c}"]) * (F.col(d) - own[f"c{c}"])
        part = x if part is None else part + x
    return assigned.agg(F.sum(part).alias("sse"))
