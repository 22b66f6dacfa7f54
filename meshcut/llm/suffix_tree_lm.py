"""Language-model scoring with a probabilistic suffix tree, beside a smoothed word unigram.

The tree predicts the bytes of a text (lower-cased, white space runs as one space, one end mark) from contexts of up to
`depth` bytes. A context is retained if it stands at `least` places or more and its next-symbol distribution diverges from
that of its parent (the context without its first byte): the divergence times its places must come to `gain` nats for each
symbol that follows it. Both are absolute, so more text of a kind retains more contexts, and a rare one is retained once it
has been seen often enough, whatever the size of the corpus. Distributions are smoothed towards that of the longest retained
suffix (`trust` virtual places), the root's towards uniform. Counts, divergence tests and smoothing are joins and
aggregations of Spark, level by level; each symbol of a text is scored by the longest retained suffix of what came before it.

Up to `broadcast` entries (some 25 bytes each) the tree goes to the executors as one hash table, to which the strings of
depth + 1 symbols seen `least` times are added with what the tree says of them, as far as they fit; that changes no score.
A larger tree is never collected: the texts' strings are then counted and joined with it, level by level, shuffled.

The unigram's counts are exact and shuffled by token; the `head` most frequent tokens are broadcast, all others are joined.
Null texts are empty (one token, the end); texts are taken whole, however long; texts with a null id are training texts;
rows that repeat an id, or a whole row, are counted and scored one by one; other columns are ignored, whatever they are
called. Without training texts the unigram gives every token probability 1 and the tree is uniform.
"""

from __future__ import annotations

import math
from collections import Counter
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from meshcut.llm import common

#: Above a string's bytes in a key: symbols in the string, or 8 and more for a context's weight.
MARK = 56
SPREAD = np.uint64(0x9E3779B97F4A7C15)


def symbols(body: bytes, depth: int) -> bytes:
    return b"\n" * depth + b" ".join(body.translate(common.LOWER).split()) + b"\n"


def in_training(column):
    return F.coalesce(F.crc32(column.cast("string").cast("binary")) % 10 != 0, F.lit(True))


def gather(depth: int):
    """Rows (token, gram, n): counts of the tokens and of all strings of depth + 1 symbols."""

    def run(batches):
        words: Counter = Counter()
        held, kinds = [], 0  # distinct strings of each block, with counts
        waiting, size = [], 0

        def counted():
            nonlocal waiting, size, kinds
            # sorting values takes a tenth of sorting places by them
            codes = np.sort(np.concatenate(waiting))
            edge = np.nonzero(np.concatenate([[True], codes[1:] != codes[:-1]]))[0]
            held.append((codes[edge], np.diff(np.append(edge, len(codes)))))
            kinds += len(edge)
            waiting, size = [], 0

        def merged():
            codes, counts = (np.concatenate(x) for x in zip(*held))
            if len(held) > 1:
                order = np.argsort(codes, kind="stable")
                codes, counts = codes[order], counts[order]
                edge = np.nonzero(np.concatenate([[True], codes[1:] != codes[:-1]]))[0]
                codes, counts = codes[edge], np.add.reduceat(counts, edge)
            return codes, counts

        def out(kind):
            if kind == "words":
                token, n = list(words), list(words.values())
                words.clear()
                return pa.RecordBatch.from_arrays([pa.array(token, pa.binary()), pa.nulls(len(n), pa.int64()), pa.array(n, pa.int64())], names=["token", "gram", "n"])
            return pa.RecordBatch.from_arrays([pa.nulls(len(held[0][0]), pa.binary()), *map(pa.array, held.pop())], names=["token", "gram", "n"])

        for b in batches:
            for body in b.column(1).to_pylist():
                text = symbols(body, depth)
                words.update(text[depth:-1].split(b" ") if len(text) > depth + 1 else ())
                words[b""] += 1
                code = strings(text, depth)
                waiting.append(code)
                size += len(code)
                if size > 3_000_000:
                    counted()
                    if kinds > 2_000_000:
                        held[:] = [merged()]
                        kinds = len(held[0][0])
                        if kinds > 1_000_000:
                            yield out("grams")
                            kinds = 0
                if len(words) > 400_000:
                    yield out("words")
        if size:
            counted()
        if words:
            yield out("words")
        if held:
            held[:] = [merged()]
            yield out("grams")

    return run


def bits(n: int) -> int:
    """Mask of n bytes."""
    return (1 << 8 * n) - 1


def levels(grams: DataFrame, depth: int, least: int, gain: float, trust: float) -> tuple[list[DataFrame], int, int]:
    """Per context length 0 to depth the table (code: context and symbol, n, every: the context's places, p, retained) of all
    contexts of `least` places or more; p is what the longest retained suffix says. Also the places and the symbols."""
    total, kinds = grams.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count_distinct(F.col("gram").bitwiseAND(255))).first()
    size = kinds + 1  # one more for all symbols never seen
    out = []
    for d in range(depth + 1):
        level = grams.groupBy(F.col("gram").bitwiseAND(bits(d + 1)).alias("code")).agg(F.sum("n").alias("n"))
        if d == 0:
            level = level.select("code", "n", F.lit(total).alias("every"), ((F.col("n") + 1) / F.lit(total + size)).alias("p"), F.lit(True).alias("retained"))
        else:
            up = out[-1].select(F.col("code").alias("up"), (F.col("n") / F.col("every")).alias("share"), F.col("p").alias("before"))
            level = level.withColumns({"up": F.col("code").bitwiseAND(bits(d)), "context": F.shiftright("code", 8)}).join(up, "up")
            mine = Window.partitionBy("context")
            level = level.withColumns({"every": F.sum("n").over(mine), "kinds": F.count("*").over(mine), "nats": F.sum(F.col("n") * F.log(F.col("n") / F.col("share"))).over(mine)}).where(F.col("every") >= least)
            retained = (F.col("nats") - F.col("every") * F.log(F.col("every").cast("double"))) >= gain * F.col("kinds")
            p = F.when(retained, (F.col("n") + trust * F.col("before")) / (F.col("every") + trust)).otherwise(F.col("before"))
            level = level.select("code", "n", "every", p.alias("p"), retained.alias("retained"))
        out.append(common.written(level, "lm-level"))
    return out, total, size


def entries(tables: list[DataFrame], trust: float) -> DataFrame:
    """(key, value): log10 probabilities of the symbols of retained contexts, and what the contexts' other symbols get."""
    parts = []
    for d, t in enumerate(tables):
        kept = t.where("retained")
        parts.append(kept.select((F.col("code") + ((d + 1) << MARK)).alias("key"), F.log10("p").alias("value")))
        if d:
            other = kept.select((F.shiftright("code", 8) + ((8 + d) << MARK)).alias("key"), F.log10(F.lit(trust) / (F.col("every") + trust)).alias("value"))
            parts.append(other.dropDuplicates(["key"]))
    return reduce(DataFrame.unionByName, parts)


class Table:
    """Keys and values in open addressing, filled and searched a whole array at a time."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.power = max(4, int(2 * len(keys)).bit_length())
        self.keys, self.values = np.zeros(1 << self.power, np.int64), np.zeros(1 << self.power, np.float32)
        at, left = self.home(keys), np.arange(len(keys))
        while len(left):
            # of those that want a free place the last written has it
            free = self.keys[at[left]] == 0
            self.keys[at[left][free]] = keys[left[free]]
            done = self.keys[at[left]] == keys[left]
            self.values[at[left][done]] = values[left[done]]
            left = left[~done]
            at[left] = (at[left] + 1) & ((1 << self.power) - 1)

    def home(self, keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((keys.view(np.uint64) * SPREAD) >> np.uint64(64 - self.power)).astype(np.int64)

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(whether it is there, value) of each key; keys are never 0."""
        at = self.home(keys)
        have = self.keys[at]
        hit = have == keys
        value = self.values[at]
        left = np.nonzero(~hit & (have != 0))[0]
        while len(left):
            at[left] = (at[left] + 1) & ((1 << self.power) - 1)
            have = self.keys[at[left]]
            good = have == keys[left]
            hit[left[good]] = True
            value[left[good]] = self.values[at[left[good]]]
            left = left[~good & (have != 0)]
        return hit, value


class Tree:
    """The retained contexts as a table; scores whole texts. unseen: log10 probability of a symbol never seen."""

    def __init__(self, keys: np.ndarray, values: np.ndarray, depth: int, unseen: float):
        self.table, self.depth, self.unseen = Table(keys, values), depth, unseen

    def of_strings(self, code: np.ndarray) -> np.ndarray:
        """log10 probability of the last symbol of each string of depth + 1 symbols after the others."""
        out = np.zeros(len(code))
        left = np.arange(len(code))
        for d in range(self.depth, -1, -1):
            hit, value = self.table.find((code[left] & bits(d + 1)) | ((d + 1) << MARK))
            out[left[hit]] += value[hit]
            left = left[~hit]
            if d and len(left):
                hit, value = self.table.find(((code[left] >> 8) & bits(d)) | ((8 + d) << MARK))
                out[left[hit]] += value[hit]
        out[left] += self.unseen
        return out

    def score(self, bodies: list[bytes]) -> np.ndarray:
        out, held, size = [], [], 0
        for body in bodies:
            text = symbols(body, self.depth)
            held.append(text)
            size += len(text)
            if size > 1_000_000:
                out.append(self._score(held))
                held, size = [], 0
        if held:
            out.append(self._score(held))
        return np.concatenate(out) if out else np.empty(0)

    def _score(self, texts: list[bytes]) -> np.ndarray:
        code = strings(b"".join(texts), self.depth)
        ends = np.cumsum([len(t) for t in texts]) - self.depth
        begins = ends - [len(t) - self.depth for t in texts]
        # strings that begin in one text and end in the next do not count
        inside = np.zeros(len(code) + 1, np.int8)
        np.add.at(inside, begins, 1)
        np.add.at(inside, np.minimum(ends, len(code)), -1)
        inside = np.cumsum(inside[:-1]) > 0
        value = np.zeros(len(code))
        value[inside] = self.of_strings(code[inside])
        return np.add.reduceat(value, begins)


def strings(text: bytes, depth: int) -> np.ndarray:
    """Codes of all strings of depth + 1 symbols."""
    x = np.frombuffer(text, np.uint8).astype(np.int64)
    m = len(x) - depth
    code = np.zeros(m, np.int64)
    for j in range(depth + 1):
        code = (code << 8) | x[j : j + m]
    return code


def joined_scores(docs: DataFrame, tree: DataFrame, depth: int, unseen: float) -> DataFrame:
    """(uid, score) by joins of the texts' counted strings with the tree's entries. docs: uid, _body."""

    def count(batches):
        for b in batches:
            for uid, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                text = symbols(body, depth)
                for lo in range(0, len(text) - depth, 1_000_000):
                    code, n = np.unique(strings(text[lo : lo + 1_000_000 + depth], depth), return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(code), uid)), pa.array(code), pa.array(n)], names=["uid", "gram", "n"])

    left = docs.select("uid", "_body").mapInArrow(count, "uid long, gram long, n long").withColumn("w", F.lit(0.0))
    parts = []
    for d in range(depth, -1, -1):
        found = left.withColumn("key", F.col("gram").bitwiseAND(bits(d + 1)) + ((d + 1) << MARK)).join(tree, "key", "left").drop("key")
        found = common.written(found, "lm-joined")
        parts.append(found.where("value is not null").select("uid", (F.col("n") * (F.col("w") + F.col("value"))).alias("s")))
        left = found.where("value is null").drop("value")
        if d:
            left = left.withColumn("key", F.shiftright("gram", 8).bitwiseAND(bits(d)) + ((8 + d) << MARK)).join(tree, "key", "left")
            left = left.select("uid", "gram", "n", (F.col("w") + F.coalesce("value", F.lit(0.0))).alias("w"))
    parts.append(left.select("uid", (F.col("n") * (F.col("w") + unseen)).alias("s")))
    return reduce(DataFrame.unionByName, parts).groupBy("uid").agg(F.sum("s").alias("joined"))


SCORED = "doc_id long, uid long, n_tokens long, head_known long, head_sum double, score double, tail array<struct<token: binary, n: int>>"


def scored(docs: DataFrame, depth: int = 5, least: int = 16, gain: float = 2.0, trust: float = 4.0, head: int = 50_000, broadcast: int = 8_000_000) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    spark = docs.sparkSession
    learned = common.doc_rows(docs.where(in_training(F.col("doc_id"))))
    got = common.written(learned.mapInArrow(gather(depth), "token binary, gram long, n long"), "lm-counts")
    tokens = common.written(got.where("token is not null").groupBy("token").agg(F.sum("n").alias("c")), "lm-tokens")
    grams = common.written(got.where("gram is not null").groupBy("gram").agg(F.sum("n").alias("n")), "lm-grams")
    big_n, v = tokens.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    tables, places, size = levels(grams, depth, least, gain, trust)
    unseen = -math.log10(places + size)
    held = common.written(entries(tables, trust), "lm-tree")
    n = held.count()
    if n <= broadcast:
        # known strings of which a shorter context decides save the search for it
        often = tables[depth].where((F.col("n") >= least) & ~F.col("retained")).select((F.col("code") + ((depth + 1) << MARK)).alias("key"), F.log10("p").alias("value"))
        more = n + often.count() <= broadcast
        flat = (held.unionByName(often) if more else held).select("key", F.col("value").cast("float").alias("value")).toArrow()
        tree = Tree(flat.column("key").to_numpy(), flat.column("value").to_numpy(), depth, unseen)
    else:
        tree = None
    frequent = {bytes(r[0]): math.log10(r[1] + 0.1) for r in tokens.orderBy(F.desc("c"), "token").limit(head).collect()}
    sent = spark.sparkContext.broadcast((tree, frequent))

    def run(batches):
        tree, frequent = sent.value
        for b in batches:
            for lo in range(0, b.num_rows, 2000):
                part = b.slice(lo, 2000)
                bodies = part.column(1).to_pylist()
                n, known, sums, tails = [], [], [], []
                for body in bodies:
                    words = body.translate(common.LOWER).split()
                    have = Counter(words)
                    have[b""] += 1
                    hits, total, tail = 0, 0.0, []
                    for w, c in have.items():
                        x = frequent.get(w)
                        if x is None:
                            tail.append({"token": w, "n": c})
                        else:
                            hits += c
                            total += c * x
                    n.append(len(words) + 1)
                    known.append(hits)
                    sums.append(total)
                    tails.append(tail)
                kind = pa.list_(pa.struct([("token", pa.binary()), ("n", pa.int32())]))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(n, pa.int64()), pa.array(known, pa.int64()), pa.array(sums, pa.float64()), pa.array(tree.score(bodies) if tree else np.zeros(len(bodies))), pa.array(tails, kind)], names=["doc_id", "uid", "n_tokens", "head_known", "head_sum", "score", "tail"])

    every = common.doc_rows(docs)
    if tree is None:
        every = common.written(every.withColumn("uid", F.monotonically_increasing_id()), "lm-texts")
        rows = common.written(every.select("_id", "_body", "uid").mapInArrow(run, SCORED), "lm-scored")
        rows = rows.drop("score").join(joined_scores(every, held, depth, unseen).withColumnRenamed("joined", "score"), "uid")
    else:
        rows = every.withColumn("uid", F.monotonically_increasing_id()).mapInArrow(run, SCORED)
        rows = common.written(rows, "lm-scored")
    rest = rows.select("uid", F.explode("tail").alias("t")).select("uid", "t.token", "t.n")
    found = rest.join(tokens, "token", "left").groupBy("uid").agg(
        F.sum(F.when(F.col("c").isNotNull(), F.col("n")).otherwise(0)).alias("tail_known"),
        F.sum(F.col("n") * F.log10(F.coalesce("c", F.lit(0)) + 0.1)).alias("tail_sum"),
    )
    out = rows.drop("tail").join(found, "uid", "left")
    doc_id = common.public_id("doc_id")
    return out.select(
        doc_id.alias("doc_id"), (~in_training(doc_id)).alias("held_out"), "n_tokens",
        (F.col("head_known") + F.coalesce("tail_known", F.lit(0))).alias("n_known"),
        F.lit(int(big_n)).cast("long").alias("train_tokens"),
        (F.col("head_sum") + F.coalesce("tail_sum", F.lit(0.0)) - F.col("n_tokens") * math.log10(big_n + 0.1 * (v + 1))).alias("base_score"),
        "score",
    )


def lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(common.table(spark, sf_dir, "documents"))
