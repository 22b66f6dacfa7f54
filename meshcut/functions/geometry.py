"""Distances and the per-point assignment expression.

Centres are k rows; expressions take them as one literal array of structs (block, c0, c1, ..., influence) for small k.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def squared_distance(xs: list[Column], cs: list[Column]) -> Column:
    out = None
    for x, c in zip(xs, cs):
        part = (x - c) * (x - c)
        out = part if out is None else out + part
    return out


def effective_distance(xs: list[Column], cs: list[Column], influence: Column) -> Column:
    """Distance over the centre's influence."""
    return F.sqrt(squared_distance(xs, cs)) / influence


def centre_array(centres) -> Column:
    """A literal array of the centres of a Centres object."""
    rows = []
    for c in centres.rows:
        rows.append(F.struct(F.lit(c.block).alias("block"), *(F.lit(float(v)).alias(f"c{d}") for d, v in enumerate(c.at)), F.lit(float(c.influence)).alias("influence")))
    return F.array(*rows)


def two_nearest(xs: list[Column], centres: Column) -> Column:
    """struct(block, eff, eff2): the centre of least effective distance (ties: lowest block) and the second-least distance.

    One fold over the centres, so each distance is computed once.
    """
    far = F.lit(float("inf"))
    start = F.struct(F.lit(-1).alias("block"), far.alias("eff"), far.alias("eff2"))

    def step(a, c):
        d = F.sqrt(squared_distance(xs, [c[f"c{k}"] for k in range(len(xs))])) / c["influence"]
        # a one-element transform names d, so it is evaluated once
        return F.get(F.transform(F.array(d), lambda e: F.struct(
            F.when(e < a["eff"], c["block"]).otherwise(a["block"]).alias("block"),
            F.least(e, a["eff"]).alias("eff"),
            F.when(e < a["eff"], a["eff"]).otherwise(F.least(e, a["eff2"])).alias("eff2"),
        )), F.lit(0))

    return F.aggregate(centres, start, step)


def geometric_mean(x: Column) -> Column:
    return F.exp(F.avg(F.log(x)))


def harmonic_mean(x: Column) -> Column:
    """count / sum(1/x); 1/infinity is 0, and infinite values alone give infinity."""
    inverse = F.sum(F.when(x == float("inf"), F.lit(0.0)).otherwise(1 / x))
    return F.when(inverse == 0, F.lit(float("inf"))).otherwise(F.count(x) / inverse)
