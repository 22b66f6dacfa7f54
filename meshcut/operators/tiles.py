"""Bounding boxes of curve tiles, and the centres that can own a point of a tile."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from meshcut.operators.kmeans import Centres


def tile_boxes(points: DataFrame, dims) -> DataFrame:
    box = [f(d).alias(f"{n}_{d}") for d in dims for n, f in (("lo", F.min), ("hi", F.max))]
    return points.groupBy("tile").agg(F.count("*").alias("n"), F.sum("w").alias("w"), *box)


def centre_frame(tiles: DataFrame, centres: Centres) -> DataFrame:
    rows = [(c.block, *map(float, c.at), float(c.influence)) for c in centres.rows]
    names = ", ".join(f"c{n} double" for n in range(len(centres.rows[0].at)))
    return tiles.sparkSession.createDataFrame(rows, f"block int, {names}, influence double")


def box_distances(tiles: DataFrame, centres: Centres, dims) -> DataFrame:
    """tile, block, least_eff and most_eff: bounds of the effective distance from any point of the tile's box.

    k centres are broadcast: their number is a parameter, not the data's.
    """

    def total(parts: list[Column]) -> Column:
        out = None
        for p in parts:
            out = p * p if out is None else out + p * p
        return F.sqrt(out)

    gaps, fars = [], []
    for n, d in enumerate(dims):
        lo, hi, c = F.col(f"lo_{d}"), F.col(f"hi_{d}"), F.col(f"c{n}")
        gaps.append(F.greatest(F.lit(0.0), lo - c, c - hi))
        fars.append(F.greatest(F.abs(c - lo), F.abs(c - hi)))
    pairs = tiles.crossJoin(F.broadcast(centre_frame(tiles, centres)))
    return pairs.select("tile", "block", (total(gaps) / F.col("influence")).alias("least_eff"), (total(fars) / F.col("influence")).alias("most_eff"))


def tile_candidates(tiles: DataFrame, centres: Centres, dims) -> DataFrame:
    """Centres that can be best or second best for a point of the tile: least distance within the second-least of the largest."""
    b = box_distances(tiles, centres, dims)
    limit = b.groupBy("tile").agg(F.sort_array(F.collect_list("most_eff")).alias("m"))
    limit = limit.select("tile", F.coalesce(F.get("m", F.lit(1)), F.get("m", F.lit(0))).alias("limit"))
    return b.join(limit, "tile").where("least_eff <= limit").select("tile", "block", "least_eff")


def interior_tiles(tiles: DataFrame, centres: Centres, dims) -> DataFrame:
    """Tiles with one possible owner: its largest distance is under every other centre's least."""
    b = box_distances(tiles, centres, dims)
    w = Window.partitionBy("tile")
    best = b.withColumn("own", F.min(F.struct("most_eff", "block")).over(w))
    others = F.min(F.when(F.col("block") != F.col("own.block"), F.col("least_eff"))).over(w)
    return best.withColumn("rest", others).where((F.col("block") == F.col("own.block")) & (F.col("rest").isNull() | (F.col("rest") > F.col("most_eff")))).select("tile", "block")
