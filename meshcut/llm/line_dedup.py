"""Line dedup by winnowing: later copies of runs of lines go.

The non-blank lines of a text are hashed; in each window of `run` neighbouring hashes the least (rightmost of equals) is a
fingerprint, so a run of `run` or more lines that two texts share has a fingerprint in both. Fingerprints that occur once
are dropped; the others are extended both ways to every window of `run` lines that holds them, and windows that occurred
before (smaller id, or earlier in the same text) are deleted with the blank lines inside them. Neighbouring and overlapping
windows add up, so the whole later run goes, however long; a run that overlaps its own copy loses the copy.

Only lines' hashes, never texts or all pairs of a group, are shuffled to find repeats; counts and first positions are
combined on the map side, so a line in a third of all texts stays cheap. Texts shorter than `run` lines, null and empty
texts stay as they are. Texts are taken whole, and the time is linear in their lines.
Identical rows (same id and text) count as one place: none of them is later than the other. Other columns pass through,
whatever they are called; names that begin with `_mc_` are taken.

The query is this, as its SQL says. The pipeline stage also takes runs of fewer lines if they have `words` words or more, so
that a repeated passage goes whether it is one long line or many short ones.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.llm import common

PLACES = "print long, _id long, _th long, first int, last int, run_hash long"


def line_windows(body: bytes, run: int, words: int | None = None):
    """(fingerprint, first line, last line, window hash) of the windows around each fingerprint, and of the shorter runs of
    `words` words or more (none if null), which are their own fingerprints."""
    lines = body.split(b"\n")
    at = [i for i, x in enumerate(lines) if x.strip()]
    if len(at) < run and (words is None or not at):
        return None
    raw = b"".join([xxhash.xxh64_digest(lines[i]) for i in at])
    h = np.frombuffer(raw, ">u8").astype(np.uint64)
    at = np.array(at, np.int32)
    parts = [full_windows(h, at, run)] if len(at) >= run else []
    if words is not None:
        upto = np.cumsum([0, *(len(lines[i].split()) for i in at)])
        for n in range(1, min(run, len(at) + 1)):
            s = np.nonzero(upto[n:] - upto[:-n] >= words)[0]
            own = common.rolled(h, n)[s] ^ np.uint64(n)
            parts.append((own, at[s], at[s + n - 1], own))
    return tuple(np.concatenate(x) for x in zip(*parts))


def full_windows(h: np.ndarray, at: np.ndarray, run: int):
    chosen = common.window_minima(h, run)
    windows = common.rolled(h, run)
    p = np.repeat(chosen, run)
    s = p - np.tile(np.arange(run), len(chosen))
    fits = (s >= 0) & (s < len(windows))
    p, s = p[fits], s[fits]
    return h[p], at[s], at[s + run - 1], windows[s]


def later_lines(docs: DataFrame, run: int = 3, words: int | None = None) -> DataFrame:
    """(_id, _th, gone): the numbers of the lines to delete, for texts that have any."""

    def places(batches):
        for b in batches:
            ids, ths, cols = b.column(0).to_pylist(), b.column(2).to_pylist(), []
            for i, body, th in zip(ids, b.column(1).to_pylist(), ths):
                got = line_windows(body, run, words)
                if got is not None:
                    n = len(got[0])
                    cols.append((got[0], np.full(n, i), np.full(n, th), *got[1:]))
            if cols:
                p, i, t, a, z, w = (np.concatenate(c) for c in zip(*cols))
                yield pa.RecordBatch.from_arrays([pa.array(p.view(np.int64)), pa.array(i), pa.array(t), pa.array(a), pa.array(z), pa.array(w.view(np.int64))], names=[x.split()[0] for x in PLACES.split(", ")])

    rows = common.written(common.doc_rows(docs, common.text_hash().alias("_th")).mapInArrow(places, PLACES), "lines")
    prints = rows.select("print", "_id", "_th", "first").groupBy("print").agg(F.min("_id").alias("i0"), F.max("_id").alias("i1"), F.min("_th").alias("t0"), F.max("_th").alias("t1"), F.min("first").alias("f0"), F.max("first").alias("f1"))
    # written, so that both sides of the join come from exchanges of their own and Spark can split a hot print's rows
    repeated = common.written(prints.where("i0 <> i1 or t0 <> t1 or f0 <> f1").select("print"), "prints")
    windows = rows.join(repeated, "print", "left_semi").select("run_hash", "_id", "_th", "first", "last")
    windows = common.written(windows, "runs")
    places_of = F.struct("_id", "_th", "first")
    before = windows.groupBy("run_hash").agg(F.min(places_of).alias("origin"), F.max(places_of).alias("end")).where("origin <> end").select("run_hash", "origin")
    before = common.written(before, "origins")
    later = windows.join(before, "run_hash").where(places_of != F.col("origin"))
    return later.select("_id", "_th", F.explode(F.sequence("first", "last")).alias("line")).groupBy("_id", "_th").agg(F.collect_set("line").alias("gone"))


def dedup_lines(docs: DataFrame, run: int = 3, words: int | None = None) -> DataFrame:
    """docs with the later lines out of `text`, and `_mc_gone`, the deleted lines' numbers (null: none)."""
    common.prepare(docs.sparkSession)
    keyed = docs.withColumns({"_mc_id": F.coalesce(F.col("doc_id").cast("long"), F.lit(common.NO_ID)), "_mc_th": common.text_hash()})
    joined = keyed.join(later_lines(docs, run, words).toDF("_mc_id", "_mc_th", "_mc_gone"), ["_mc_id", "_mc_th"], "left")
    joined = joined.withColumn("_mc_lines", F.when(F.col("_mc_gone").isNotNull(), F.split("text", "\n")))
    left = F.array_except(F.sequence(F.lit(0), F.size("_mc_lines") - 1), F.col("_mc_gone"))
    rest = F.array_join(F.transform(left, lambda i: F.get("_mc_lines", i)), "\n")
    return joined.withColumn("text", F.when(F.col("_mc_gone").isNotNull(), rest).otherwise(F.col("text"))).drop("_mc_id", "_mc_th", "_mc_lines")


def line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_removed (lines), kept_sha256 of every document."""
    out = dedup_lines(common.table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.coalesce(F.size("_mc_gone"), F.lit(0)).cast("long").alias("n_removed"), F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("kept_sha256"))


def drop_later_lines(spark: SparkSession, docs: DataFrame, sf_dir: str, words: int = 50) -> DataFrame:
    """Pipeline stage: every row stays, with its later lines gone; n_chars follows the text."""
    out = dedup_lines(docs, words=words)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_mc_gone").isNotNull(), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)
