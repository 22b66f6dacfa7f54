"""Near-duplicate stage: SimHash candidates on five-word shingles, kept if their shingle sets are 0.8 alike or more.

Documents with equal word sequences are one class to begin with. Texts whose Jaccard similarity is 0.8 differ in some 15 %
of their fingerprint bits, so one 64-bit fingerprint with a small radius would miss them. Each text gets eight independent
46-bit fingerprints (two 23-bit vectors each, from eight remixes of the shingle hashes); texts share a bucket of a
fingerprint if both vectors have a Golay key in common, which holds whenever both are at most two bits apart. All members of
a bucket are compared on 64 other bits, so unrelated texts that crowd a bucket neither hide a pair nor pass for one; a
bucket gives the links that span its members within `radius`, crowded ones block against block. The links' components are
candidate groups: in each, the shingle sets of all texts are compared with one another, groups over `BLOCK` texts block
against block, and the links that stand form the classes. Of each class the document with the least id stays (of equal ids
the first text by hash).

Of 700 pairs each, 98.1 % were candidates at a similarity of 0.80 to 0.82 and 99.4 % at 0.82 to 0.86; a pair that is no
candidate itself is still found if a chain of candidates joins it. Null and empty texts are alike; texts are taken whole,
however long; a null id sorts first; rows that repeat an id with another text are documents of their own, and of identical
rows one stays; other columns pass through, whatever they are called, but for names that begin with `_mc_`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.llm import common, simhash

TABLES = 8
#: Texts of a candidate group that are compared with one another at once.
BLOCK = 512
WORD = np.uint64((1 << 23) - 1)


def signature(raw: bytes) -> tuple[int, int, list[int]]:
    """Two 64-bit fingerprints and the eight 46-bit ones, of a text's shingle digests.

    The first shares bits with tables 0 and 1, the other with tables 6 and 7.
    """
    if not raw:
        return 0, 0, [0] * TABLES
    h = np.unique(np.frombuffer(raw, ">u8").astype(np.uint64))
    words = [h]
    with np.errstate(over="ignore"):
        for t in range(1, 6):
            x = h * np.uint64(2 * t * 0x9E3779B97F4A7C15 + 1 & 2**64 - 1)
            words.append(x ^ (x >> np.uint64(31)))
    bits = np.stack([np.unpackbits(np.ascontiguousarray(w.astype(">u8")).view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64) for w in words])
    on = (2 * bits > len(h)).astype(np.uint8)
    base, other = (int.from_bytes(np.packbits(on[k]).tobytes(), "big") for k in (0, 5))
    flat = on.ravel()[: 46 * TABLES].reshape(TABLES, 46)
    power = np.int64(1) << np.arange(46, dtype=np.int64)
    return base, other, (flat * power).sum(axis=1).tolist()


def signatures(docs: DataFrame, size: int) -> DataFrame:
    """(_id, _th, _h, fp, other, sigs) of every row: _h is the hash of the word sequence. No text leaves the map."""

    def run(batches):
        for b in batches:
            bodies = b.column(1).to_pylist()
            h = [xxhash.xxh64_intdigest(b" ".join(x.translate(common.LOWER).split())) for x in bodies]
            sig = [signature(simhash.shingle_digests(x, size)) for x in bodies]
            fp, other = (np.array([s[k] for s in sig], np.uint64).view(np.int64) for k in (0, 1))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(np.array(h, np.uint64).view(np.int64)), pa.array(fp), pa.array(other), pa.array([s[2] for s in sig], pa.list_(pa.int64()))], names=["_id", "_th", "_h", "fp", "other", "sigs"])

    rows = common.doc_rows(docs, common.text_hash().alias("_th"))
    return rows.mapInArrow(run, "_id long, _th long, _h long, fp long, other long, sigs array<bigint>")


def bucket_rows(batches):
    """(key, fp) of every bucket of the eight fingerprints of (fp, other, sigs) rows; fp shares no bits with the key."""
    errors = simhash.error_table()
    for b in batches:
        fp, other = (b.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
        sigs = np.array(b.column(2).to_pylist(), np.int64).reshape(len(fp), TABLES).astype(np.uint64)
        for lo in range(0, len(fp), 10000):
            for t in range(TABLES):
                v, judge = sigs[lo : lo + 10000, t], (other if t < 2 else fp)[lo : lo + 10000]
                one = simhash.golay_keys((v & WORD).astype(np.uint32), errors)
                two = simhash.golay_keys((v >> np.uint64(23)).astype(np.uint32), errors)
                fresh = [np.concatenate([np.ones((len(v), 1), bool), k[:, 1:] != k[:, :1]], axis=1) for k in (one, two)]
                keys, rows = [], []
                for i in range(6):
                    for j in range(6):
                        r = np.nonzero(fresh[0][:, i] & fresh[1][:, j])[0]
                        keys.append((t << 24) | (one[r, i].astype(np.int32) << 12) | two[r, j].astype(np.int32))
                        rows.append(r)
                r = np.concatenate(rows)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys).astype(np.int32)), pa.array(judge[r])], names=["key", "fp"])


def candidate_links(classes: DataFrame, radius: int) -> DataFrame:
    """(a, b): links of class hashes that span the candidate groups. classes: one row a class, with _h, fp, other and sigs."""
    parts = int(classes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = classes.select("fp", "other", "sigs").repartition(parts).mapInArrow(bucket_rows, "key int, fp long")
    pairs = common.written(simhash.bucket_links(rows, radius, sifted=32), "near")
    # a word stands for all classes that have it as either fingerprint: those are candidates too
    words = classes.select("_h", F.explode(F.array_distinct(F.array("fp", "other"))).alias("w"))
    heads = words.groupBy("w").agg(F.min("_h").alias("head"), F.max("_h").alias("last"))
    one, two = (heads.select(F.col("w").alias(f), F.col("head").alias(h)) for f, h in (("fa", "a"), ("fb", "b")))
    across = pairs.toDF("fa", "fb").join(one, "fa").join(two, "fb").select("a", "b")
    inside = words.join(heads.where("head <> last"), "w").where("_h <> head").select(F.col("head").alias("a"), F.col("_h").alias("b"))
    return common.written(across.unionByName(inside).where("a <> b"), "near-candidates")


def alike(sets: list[np.ndarray], block: np.ndarray, least: float) -> list[tuple[int, int]]:
    """A spanning forest of the pairs of sets that are `least` alike; with two blocks, of the pairs across."""
    n, across = len(sets), len(set(block.tolist())) > 1
    size = np.array([len(s) for s in sets])
    if n <= 8:
        near = np.zeros((n, n), bool)
        for i in range(n):
            for j in range(i):
                both = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
                near[i, j] = near[j, i] = both >= least * (size[i] + size[j] - both)
    else:
        # shingles of one set only add nothing to an intersection
        values, column, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        row = np.repeat(np.arange(n), size)
        shared = often[column] > 1
        row, column = row[shared], (np.cumsum(often > 1) - 1)[column[shared]]
        order = np.argsort(column, kind="stable")
        row, column = row[order], column[order]
        both = np.zeros((n, n), np.float32)
        for lo in range(0, int((often > 1).sum()), 4096):
            s, e = np.searchsorted(column, [lo, lo + 4096])
            x = np.zeros((n, 4096), np.float32)
            x[row[s:e], column[s:e] - lo] = 1
            both += x @ x.T
        near = both >= least * (size[:, None] + size[None, :] - both.astype(np.float64))
    if across:
        near &= block[:, None] != block[None, :]
    left, out = np.ones(n, bool), []
    for start in range(n):
        front = [start] if left[start] else []
        left[start] = False
        while front:
            at = front.pop()
            got = np.nonzero(near[at] & left)[0].tolist()
            left[got] = False
            out += [(at, g) for g in got]
            front += got
    return out


def compare(size: int, least: float):
    """Rows (key, _h, block, body) where equal keys are neighbours: links (a, b) of the texts of each key."""

    def run(batches):
        now, held, found = None, [], []

        def flush():
            if len(held) > 1:
                sets = [np.unique(np.frombuffer(simhash.shingle_digests(x[2], size), ">u8").astype(np.uint64)) for x in held]
                found.extend((held[i][0], held[j][0]) for i, j in alike(sets, np.array([x[1] for x in held]), least))

        def out():
            nonlocal found
            a, b = zip(*found) if found else ((), ())
            found = []
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

        for b in batches:
            for key, h, block, body in zip(*(c.to_pylist() for c in b.columns)):
                if key != now:
                    flush()
                    now, held = key, []
                held.append((h, block, body))
            if found:
                yield out()
        flush()
        yield out()

    return run


def verified(groups: DataFrame, texts: DataFrame, size: int, least: float) -> DataFrame:
    """(a, b): links that span the classes. groups: (node, component) of candidates; texts: _h, _body."""
    many = groups.groupBy("component").agg(F.count("*").alias("n"))
    blocks = groups.join(many, "component").select(F.col("node").alias("_h"), "component", F.ceil(F.col("n") / BLOCK).cast("int").alias("m"))
    blocks = blocks.withColumn("block", F.pmod(F.xxhash64("_h"), F.col("m")).cast("int")).join(texts, "_h")
    # block i meets every block j, and itself: its rows go to the pairs (i, j) and (j, i)
    pair = blocks.withColumn("j", F.explode(F.sequence(F.lit(0), F.col("m") - 1)))
    dealt = pair.select(F.xxhash64("component", F.least("block", "j"), F.greatest("block", "j")).alias("key"), "_h", "block", "_body")
    return dealt.repartition("key").sortWithinPartitions("key").mapInArrow(compare(size, least), "a long, b long")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str, size: int = 5, least: float = 0.8, radius: int = 16) -> DataFrame:
    """Pipeline stage: one document of each class stays, with all columns."""
    common.prepare(spark)
    rows = common.written(signatures(docs, size), "near-rows")
    # the text that stands for a class is that of its first row
    first = F.min(F.struct("_id", "_th", "fp", "other", "sigs"))
    classes = common.written(rows.groupBy("_h").agg(first.alias("_first")).select("_h", "_first.*"), "near-classes")
    links = candidate_links(classes, radius)
    common.release(spark)
    groups = common.written(common.connected_components(links), "near-groups")
    used = groups.select(F.col("node").alias("_h")).join(classes, "_h").select("_h", "_id", "_th")
    keyed = docs.withColumns({"_mc_id": F.coalesce(F.col("doc_id").cast("long"), F.lit(common.NO_ID)), "_mc_th": common.text_hash()})
    texts = keyed.select(F.col("_mc_id").alias("_id"), F.col("_mc_th").alias("_th"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("_body")).join(used, ["_id", "_th"]).select("_h", "_body")
    texts = common.written(texts.groupBy("_h").agg(F.first("_body").alias("_body")), "near-texts")
    common.release(spark)
    found = common.connected_components(common.written(verified(groups, texts, size, least), "near-links"))
    named = classes.join(found.withColumnRenamed("node", "_h"), "_h", "left").select(F.coalesce("component", "_h").alias("_c"), F.struct("_id", "_th").alias("_first"))
    kept = named.groupBy("_c").agg(F.min("_first").alias("_first")).select(F.col("_first._id").alias("_mc_id"), F.col("_first._th").alias("_mc_th"))
    out = keyed.join(kept, ["_mc_id", "_mc_th"], "left_semi")
    # identical rows of a class differ in no key: one of them stays
    twice = rows.groupBy("_id", "_th").count().where("count > 1")
    if twice.limit(1).count():
        out = out.dropDuplicates(["_mc_id", "_mc_th"])
    return out.select(*docs.columns)
