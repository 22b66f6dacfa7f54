"""Toxicity: a linear classifier on character n-grams scaled by naive Bayes log-count ratios.

Features are the distinct n-grams (3 to 5 bytes of the lower-cased UTF-8 text, white space runs as one space), hashed to
2**18 slots. A slot's value is the log ratio of the smoothed shares of toxic and clean training texts that have it; a
logistic regression on these values gives the score; slots whose
shares differ by less than `least_z` standard errors are left out. Null and empty texts have the n-grams of one space. Rows without a
label, or whose label is null, are not learned from; without rows of both classes every score is the share of toxic rows
among those there are (0 if none). Labels that repeat an id count once, as toxic if any says so; of texts that repeat a
labelled id the least is learned. A document with a null id is scored, never learned from nor held out; repeated rows get
equal scores. Texts are taken whole, however long; columns of other names pass through, whatever they are called.

The fit uses a bounded sample: the `per_class` labelled rows of either class with the least hash of their id, weighted
back to the true class shares. That sample is fitted in one task; scoring is one map over all documents.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.llm import common

SLOTS = 1 << 18
SIZES = (3, 4, 5)


def feature_slots(body: bytes, place: np.ndarray) -> np.ndarray:
    """The distinct slots of a text. place: int32 scratch of SLOTS entries, any content."""
    b = np.frombuffer(b" " + b" ".join(body.translate(common.LOWER).split()) + b" ", np.uint8).astype(np.uint32)
    found = []
    for n in SIZES:
        m = len(b) - n + 1
        if m <= 0:
            continue
        h = np.full(m, n, np.uint32)
        for j in range(n):
            h *= np.uint32(0x01000193)
            h ^= b[j : j + m]
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x2C1B3C6D)
        found.append(h >> np.uint32(14))
    if not found:
        return np.empty(0, np.int32)
    s = np.concatenate(found).astype(np.int32)
    order = np.arange(len(s), dtype=np.int32)
    place[s] = order
    return s[place[s] == order]


def fit(bodies: list[bytes], toxic: np.ndarray, weight: np.ndarray, smooth: float = 1.0, least_z: float = 4.0, ridge: float = 0.1, steps: int = 150):
    """Slot weights (float32, ratios already multiplied in) and the constant."""
    share = float((toxic * weight).sum() / weight.sum()) if len(toxic) else 0.0
    if share in (0.0, 1.0):
        edge = {0.0: -30.0, 1.0: 30.0}[share]
        return np.zeros(SLOTS, np.float32), edge
    place = np.zeros(SLOTS, np.int32)
    rows = [feature_slots(x, place) for x in bodies]
    counts = [smooth + np.bincount(np.concatenate([r for r, t in zip(rows, toxic) if t == k]), minlength=SLOTS) for k in (1, 0)]
    n = [(toxic == 1).sum() + 2 * smooth, (toxic == 0).sum() + 2 * smooth]
    shares = [c / k for c, k in zip(counts, n)]
    ratio = np.log(shares[0] / shares[1]).astype(np.float32)
    both = (counts[0] + counts[1]) / (n[0] + n[1])
    spread = np.sqrt(np.maximum(both * (1 - both), 1e-12) * (1 / n[0] + 1 / n[1]))
    ratio[np.abs(shares[0] - shares[1]) < least_z * spread] = 0
    rows = [r[ratio[r] != 0] for r in rows]
    ends = np.cumsum([len(x) for x in rows])
    begins = ends - [len(x) for x in rows]
    flat = np.concatenate(rows)
    value = ratio[flat]
    w = np.zeros(SLOTS, np.float32)
    bias = np.float64(np.log(share / (1 - share)))
    part = (weight / weight.sum()).astype(np.float64)
    m, v, mb, vb = np.zeros(SLOTS), np.zeros(SLOTS), 0.0, 0.0
    for t in range(1, steps + 1):
        z = np.add.reduceat(np.append(value * w[flat], np.float32(0)), begins) * (ends > begins) + bias
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        err = part * (p - toxic)
        g = np.bincount(flat, weights=value * np.repeat(err, ends - begins).astype(np.float32), minlength=SLOTS) + ridge * w / 100
        gb = err.sum()
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        mb, vb = 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
        rate = 0.02 * (1 - t / (steps + 1)) + 1e-3
        w -= (rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-7)).astype(np.float32)
        bias -= rate * (mb / (1 - 0.9**t)) / (np.sqrt(vb / (1 - 0.99**t)) + 1e-7)
    return w * ratio, float(bias)


def _fit_task(batches):
    bodies, toxic, weight = [], [], []
    for b in batches:
        bodies += b.column(0).to_pylist()
        toxic += b.column(1).to_pylist()
        weight += b.column(2).to_pylist()
    w, bias = fit(bodies, np.array(toxic, np.float64), np.array(weight, np.float64))
    yield pa.RecordBatch.from_arrays([pa.array([w.astype("<f4").tobytes()], pa.binary()), pa.array([bias])], names=["w", "bias"])


def train(docs: DataFrame, labels: DataFrame, per_class: int = 4000):
    """Learns from labelled rows whose crc32(doc_id as text) mod 5 is not 0. Returns (slot weights as bytes, constant)."""
    lab = (
        labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0))
        .groupBy(F.col("doc_id").cast("long").alias("_id")).agg(F.max((F.col("toxic") == 1).cast("int")).alias("_toxic"))
    )
    sums = {r[0]: r[1] for r in lab.groupBy("_toxic").count().collect()}
    picked = None
    for k in (0, 1):
        one = lab.where(F.col("_toxic") == k).orderBy(F.xxhash64("_id"), "_id").limit(per_class)
        weight = sums.get(k, 0) / max(1, min(per_class, sums.get(k, 0)))
        one = one.withColumn("_weight", F.lit(float(weight)))
        picked = one if picked is None else picked.unionByName(one)
    # bounded by 2 * per_class rows, whatever the input
    rows = common.doc_rows(docs).join(F.broadcast(picked), "_id").groupBy("_id").agg(F.min("_body").alias("_body"), F.first("_toxic").alias("_toxic"), F.first("_weight").alias("_weight"))
    got = rows.select("_body", "_toxic", "_weight").orderBy(F.xxhash64("_body")).coalesce(1).mapInArrow(_fit_task, "w binary, bias double").first()
    if got is None:  # no rows to learn from
        return np.zeros(SLOTS, "<f4").tobytes(), -30.0
    return bytes(got[0]), got[1]


def score_documents(docs: DataFrame, model, *keep: str, name: str = "score") -> DataFrame:
    """Adds the score (0 to 1) to the columns named in keep."""
    spark = docs.sparkSession
    packed = spark.sparkContext.broadcast(model)
    fields = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keep)

    def run(batches):
        raw, bias = packed.value
        w = np.frombuffer(raw, "<f4")
        place = np.zeros(SLOTS, np.int32)
        for b in batches:
            z = np.array([w[feature_slots(x, place)].sum(dtype=np.float64) for x in b.column(0).to_pylist()], np.float64) + bias
            s = 1 / (1 + np.exp(-np.clip(z, -500, 500)))
            yield pa.RecordBatch.from_arrays([*b.columns[1:], pa.array(s, pa.float64())], names=[*keep, name])

    common.prepare(spark)
    body = F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("_mc_body")
    return docs.select(body, *keep).mapInArrow(run, f"{fields}, {name} double")


def toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    model = train(docs, common.table(spark, sf_dir, "labels"))
    scored = score_documents(docs, model, "doc_id")
    return scored.select(
        "doc_id",
        F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
    )


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: rows scored 0.5 or more go, all columns stay."""
    common.prepare(spark)
    model = train(docs, common.table(spark, sf_dir, "labels"))
    return score_documents(docs, model, *docs.columns, name="_mc_score").where("_mc_score < 0.5").select(*docs.columns)
