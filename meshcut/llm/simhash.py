"""SimHash near-duplicates: candidates through the perfect binary Golay code, links verified, classes by components.

A fingerprint sums the bits of shingle hashes: bit i is set if more than half of the shingle hashes set it. To find
fingerprints within `radius` bits, they are cut into three segments of 22, 21 and 21 bits, each read as a 23-bit vector.
The code (23, 12, 7) decodes any vector to its one codeword within 3 bits; a segment's keys are the codewords of the
vector and of its 23 neighbours (one or six different ones), so two segments at most two bits apart share a key. With 4
errors over three segments, the two best segments have at most 2 together: joining on the keys of two segments (24 bits)
finds every pair. Pairs that share a key are verified on all bits.

Each bucket gives a spanning forest of its links, not all pairs; buckets over `hot` fingerprints are streamed out, split
into blocks by fingerprint hash and compared block against block, so no task holds an unbounded bucket and no link is lost.

Null texts and texts without words have fingerprint zero, linked like any other. Rows repeating an id or a text link as
other rows do. A null doc_id keeps its row; it never names a component unless all its members are null.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.llm import common

#: Fixed value: generator polynomial of the (23, 12, 7) Golay code, x^11 + x^10 + x^6 + x^5 + x^4 + x^2 + 1.
GENERATOR = 0b110001110101
SEGMENTS = ((0, 22), (22, 21), (43, 21))
PAIRS = ((0, 1), (0, 2), (1, 2))


def syndrome_of(v: np.ndarray) -> np.ndarray:
    """Remainder modulo the generator, of 23-bit vectors."""
    r = v.astype(np.uint32).copy()
    for k in range(22, 10, -1):
        r ^= ((r >> np.uint32(k)) & np.uint32(1)) * np.uint32(GENERATOR << (k - 11))
    return r


def error_table() -> np.ndarray:
    """For each of the 2048 syndromes the one error pattern of at most 3 bits."""
    bits = [1 << k for k in range(23)]
    patterns = [0, *bits]
    patterns += [a | b for i, a in enumerate(bits) for b in bits[:i]]
    patterns += [a | b | c for i, a in enumerate(bits) for j, b in enumerate(bits[:i]) for c in bits[:j]]
    p = np.array(patterns, np.uint32)
    out = np.zeros(2048, np.uint32)
    out[syndrome_of(p)] = p
    return out


def decode(v: np.ndarray, errors: np.ndarray) -> np.ndarray:
    """Index (the 12 message bits) of the nearest codeword."""
    return ((v ^ errors[syndrome_of(v)]) >> np.uint32(11)).astype(np.uint32)


def golay_keys(v: np.ndarray, errors: np.ndarray) -> np.ndarray:
    """(n, 6) codeword indices of each vector and its neighbours, ascending; repeats of the first fill the row."""
    near = np.stack([decode(v, errors), *(decode(v ^ np.uint32(1 << k), errors) for k in range(23))], axis=1)
    near.sort(axis=1)
    fresh = np.ones(near.shape, bool)
    fresh[:, 1:] = near[:, 1:] != near[:, :-1]
    rank = fresh.cumsum(axis=1) - 1
    out = np.repeat(near[:, :1], 6, axis=1)
    r, c = np.nonzero(fresh)
    out[r, rank[r, c]] = near[r, c]
    return out


def bucket_keys(fp: np.ndarray, errors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(key, row) of every bucket of 64-bit fingerprints."""
    seg = [((fp >> np.uint64(lo)) & np.uint64((1 << n) - 1)).astype(np.uint32) for lo, n in SEGMENTS]
    keys = [golay_keys(s, errors) for s in seg]
    fresh = [np.concatenate([np.ones((len(fp), 1), bool), k[:, 1:] != k[:, :1]], axis=1) for k in keys]
    out_k, out_r = [], []
    for t, (a, b) in enumerate(PAIRS):
        for i in range(6):
            for j in range(6):
                rows = np.nonzero(fresh[a][:, i] & fresh[b][:, j])[0]
                out_k.append((np.int64(t) << 24) | (keys[a][rows, i].astype(np.int64) << 12) | keys[b][rows, j])
                out_r.append(rows)
    return np.concatenate(out_k), np.concatenate(out_r)


def shingle_digests(body: bytes, size: int) -> bytes:
    """The 8-byte big-endian XXH64 (seed 42) of each shingle of `size` words, joined."""
    words = body.translate(common.LOWER).split()
    if not words:
        return b""
    if len(words) <= size:
        return xxhash.xxh64_digest(b" ".join(words), 42)
    flat = b" ".join(words)
    n = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(n + 1) - 1
    first, last = (ends - n).tolist(), ends[size - 1 :].tolist()
    digest = xxhash.xxh64_digest
    return b"".join([digest(flat[a:b], 42) for a, b in zip(first, last)])


def majority(raw: bytes) -> int:
    """Fingerprint of the digests."""
    if not raw:
        return 0
    bits = np.unpackbits(np.frombuffer(raw, np.uint8).reshape(-1, 8), axis=1)
    return int.from_bytes(np.packbits(2 * bits.sum(axis=0, dtype=np.int64) > len(bits)).tobytes(), "big")


def fingerprints(docs: DataFrame, size: int = 4) -> DataFrame:
    """(_id, fp): fp is the unsigned fingerprint's bits as a long."""

    def run(batches):
        for b in batches:
            fp = np.array([majority(shingle_digests(x, size)) for x in b.column(1).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], names=["_id", "fp"])

    return common.doc_rows(docs).mapInArrow(run, "_id long, fp long")


def _emit(a, b, k, f):
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(k, pa.int64()), pa.array(f, pa.int64())], names=["a", "b", "hot_key", "hot_fp"])


def forest(fp: np.ndarray, radius: int) -> tuple[list, list]:
    """A spanning forest of the links (at most `radius` bits) among fingerprints."""
    left = np.arange(len(fp))
    a, b = [], []
    while len(left):
        front, left = [left[0]], left[1:]
        while front and len(left):
            at = front.pop()
            near = np.bitwise_count(fp[left] ^ fp[at]) <= radius
            got = left[near]
            left = left[~near]
            a += [fp[at]] * len(got)
            b += fp[got].tolist()
            front += got.tolist()
    return a, b


def scan_buckets(radius: int, hot: int, sifted: int = 4):
    """Reads (key, fp) rows where equal keys are neighbours; gives links and, for keys over `hot` rows, those rows.

    Buckets of up to `sifted` rows are first searched for any link all at once, for data where most have none.
    """
    none = np.empty(0, np.int64)

    def links(key, fp):
        """All but the last key's rows are complete here."""
        u = fp.view(np.uint64)
        edge = np.nonzero(np.diff(key))[0] + 1
        starts, ends = np.append(0, edge), np.append(edge, len(key))
        n = ends - starts
        a, b = [none], [none]
        small = n <= 4
        row_small = np.repeat(small, n)
        for off in (1, 2, 3):
            if len(key) > off:
                near = (key[off:] == key[:-off]) & row_small[off:] & (np.bitwise_count(u[off:] ^ u[:-off]) <= radius) & (u[off:] != u[:-off])
                a.append(fp[:-off][near])
                b.append(fp[off:][near])
        more = ~small
        if sifted > 4:
            middle = more & (n <= sifted)
            bucket, hit = np.repeat(np.arange(len(n)), n), np.zeros(len(n), bool)
            of_middle = np.nonzero(middle[bucket])[0]
            g, v = bucket[of_middle], u[of_middle]
            for off in range(1, int(n[middle].max(initial=1))):
                near = (g[off:] == g[:-off]) & (np.bitwise_count(v[off:] ^ v[:-off]) <= radius) & (v[off:] != v[:-off])
                hit[g[off:][near]] = True
            more &= ~middle | hit
        for s, e in zip(starts[more], ends[more]):
            x, y = forest(np.unique(u[s:e]), radius)
            if x:
                a.append(np.array(x, np.uint64).view(np.int64))
                b.append(np.array(y, np.uint64).view(np.int64))
        a, b = np.concatenate(a), np.concatenate(b)
        pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0) if len(a) else np.empty((0, 2), np.int64)
        return pairs[:, 0], pairs[:, 1]

    def run(batches):
        held_k, held_f, spilling = none, none, None
        for batch in batches:
            k, f = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)
            if spilling is not None:
                m = int(np.searchsorted(k != spilling, True)) if k[0] == spilling else 0
                if k[0] == spilling and m:
                    yield _emit([None] * m, [None] * m, k[:m], f[:m])
                    k, f = k[m:], f[m:]
                if not len(k):
                    continue
                spilling = None
            k, f = np.concatenate([held_k, k]), np.concatenate([held_f, f])
            cut = int(np.nonzero(k != k[-1])[0][-1]) + 1 if k[0] != k[-1] else 0
            whole_k, whole_f, held_k, held_f = k[:cut], f[:cut], k[cut:], f[cut:]
            if len(held_k) > hot:
                spilling = held_k[0]
                yield _emit([None] * len(held_k), [None] * len(held_k), held_k, held_f)
                held_k, held_f = none, none
            yield from part(whole_k, whole_f)
        yield from part(held_k, held_f)

    def part(k, f):
        if not len(k):
            return
        edge = np.nonzero(np.diff(k))[0] + 1
        n = np.diff(np.concatenate([[0], edge, [len(k)]]))
        big = np.repeat(n > hot, n)
        if big.any():
            m = int(big.sum())
            yield _emit([None] * m, [None] * m, k[big], f[big])
            k, f = k[~big], f[~big]
        if len(k):
            a, b = links(k, f)
            if len(a):
                yield _emit(a, b, [None] * len(a), [None] * len(a))

    return run


def linked(fps: DataFrame, radius: int = 4, hot: int = 2048, keys=bucket_keys) -> DataFrame:
    """(a, b): links that span the components of all fingerprints (column fp, distinct) within `radius` bits."""
    common.prepare(fps.sparkSession)

    def expand(batches):
        errors = error_table()
        for batch in batches:
            fp = batch.column(0).to_numpy(zero_copy_only=False)
            for lo in range(0, len(fp), 20000):
                x = fp[lo : lo + 20000]
                k, r = keys(np.ascontiguousarray(x).view(np.uint64), errors)
                yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(x[r])], names=["key", "fp"])

    return bucket_links(fps.select("fp").mapInArrow(expand, "key long, fp long"), radius, hot)


def bucket_links(rows: DataFrame, radius: int, hot: int = 2048, sifted: int = 4) -> DataFrame:
    """(a, b): links that span the components of the fingerprints of every bucket, of (key, fp) rows."""
    schema = "a long, b long, hot_key long, hot_fp long"
    buckets = rows.repartition("key").sortWithinPartitions("key")
    first = common.written(buckets.mapInArrow(scan_buckets(radius, hot, sifted), schema), "buckets")
    out = first.where("a is not null").select("a", "b")
    rows = first.where("hot_key is not null").select(F.col("hot_key").alias("key"), F.col("hot_fp").alias("fp")).distinct()
    if rows.limit(1).count():
        blocks = rows.join(rows.groupBy("key").agg(F.count("*").alias("n")), "key")
        blocks = blocks.withColumn("m", F.ceil(F.col("n") / (hot / 2))).withColumn("i", F.pmod(F.xxhash64("fp"), F.col("m")))
        # block i meets every block j: its rows go to the pairs (i, j) and (j, i)
        pair = blocks.withColumn("j", F.explode(F.sequence(F.lit(0), F.col("m") - 1)))
        dealt = pair.select(F.xxhash64("key", F.least("i", "j"), F.greatest("i", "j")).alias("key"), "fp").repartition("key").sortWithinPartitions("key")
        out = out.unionByName(dealt.mapInArrow(scan_buckets(radius, 1 << 60), schema).where("a is not null").select("a", "b"))
    return out.distinct()


def components_by_fingerprint(rows: DataFrame, radius: int) -> DataFrame:
    """rows: (_id, fp). Adds component, the least id among documents whose fingerprints are linked."""
    fps = rows.groupBy("fp").agg(F.min(common.public_id("_id")).alias("least"))
    found = common.connected_components(linked(fps, radius))
    named = fps.join(found.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    named = named.select("fp", F.col("component").alias("root"), "least")
    best = named.groupBy("root").agg(F.min("least").alias("component"))
    return rows.join(named.select("fp", "root").join(best, "root").select("fp", "component"), "fp")


def simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, fingerprint, component_id of every document (4-word shingles, at most 4 bits)."""
    docs = common.table(spark, sf_dir, "documents")
    rows = common.written(fingerprints(docs, 4), "fingerprints")
    out = components_by_fingerprint(rows, 4)
    return out.select(
        common.public_id("_id").alias("doc_id"),
        F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"),
        F.col("component").alias("component_id"),
    )
