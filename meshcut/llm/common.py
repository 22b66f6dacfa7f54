"""Shared pieces of the training-data operators: shared scratch tables, bytes of a text, winnowing, components.

Conventions every operator follows: a null text counts as empty; a null ``doc_id`` keeps its row and sorts before all
others; rows that repeat a ``doc_id`` are told apart by the hash of their text, and identical rows get identical results.
"""

from __future__ import annotations

import ctypes
import gc
import os
from contextlib import contextmanager
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.sources.scratch import discard, written

REPO_ROOT = str(Path(__file__).resolve().parents[2])
#: A-Z to a-z, every other byte as it is.
LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
#: Stands for a null id inside the operators.
NO_ID = -(2**63)
#: The white space that separates words, as a regular expression class.
BLANK = r"[\x20\x09-\x0D]"


def prepare(spark: SparkSession) -> None:
    """Lets Python workers that this session starts import the package when it is not installed."""
    env = spark.sparkContext.environment
    if REPO_ROOT not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (REPO_ROOT, env.get("PYTHONPATH", "")) if x)


def release(spark: SparkSession) -> None:
    """Lets Spark remove the shuffle files of finished steps now, not when the driver next collects its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


@contextmanager
def small_batches(spark: SparkSession, size: int):
    """Steps that run inside hand Python about `size` bytes at once, which bounds the memory of both sides; afterwards the
    session is as it was."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, size)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def handing_back(run):
    """run, a function for mapInArrow; at its end the worker, which other tasks use again, gives its free memory back."""

    def whole(batches):
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim is not None:
            trim(0)

    return whole


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def doc_rows(docs: DataFrame, *more: Column) -> DataFrame:
    """_id (never null), _body (bytes, never null) and more columns of a table of documents."""
    prepare(docs.sparkSession)
    return docs.select(
        F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("_id"),
        F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("_body"),
        *more,
    )


def text_hash() -> Column:
    """Tells apart the texts of rows that repeat an id."""
    return F.xxhash64(F.coalesce(F.col("text"), F.lit("")))


def public_id(column: str) -> Column:
    return F.when(F.col(column) != NO_ID, F.col(column))


def window_minima(h: np.ndarray, width: int) -> np.ndarray:
    """Sorted positions chosen by winnowing: in each window of `width` hashes the least, the rightmost of equals.

    Shorter sequences are one window. Two sequences that share `width` neighbouring hashes share a chosen one.
    """
    n = len(h)
    if n == 0:
        return np.empty(0, np.int64)
    if width <= 1:
        return np.arange(n)
    width = min(width, n)
    best, span = np.arange(n), 1
    while span < width:
        # two windows side by side, at the end overlapping ones
        by = min(span, width - span)
        one, two = best[: len(best) - by], best[by:]
        best = np.where(h[two] <= h[one], two, one)
        span += by
    return np.unique(best)


MIX = np.uint64(0x9E3779B97F4A7C15)


def rolled(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all runs of k neighbouring word hashes (uint64, wrapping)."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    with np.errstate(over="ignore"):
        for j in range(k):
            out = (out ^ h[j : j + n]) * MIX
            out ^= out >> np.uint64(29)
    return out


def connected_components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, component) for every node of the undirected edges (a, b); a component is named by its least node.

    Alternates the two star contractions of the published map-reduce algorithm; each round is two group-bys and two joins
    whose result is written to the shared folder, so the lineage stays short. Nothing of the graph reaches the driver but
    a count and a checksum.
    """
    e = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now = written(e, "cc")
    seen = None
    for _ in range(rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        step = written(large, "cc")
        low = step.groupBy("u").agg(F.min("v").alias("m"))
        small = step.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        after = written(small, "cc")
        mark = after.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        discard(now, step)
        now = after
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError("components did not settle; raise rounds")
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
