"""Benchmark decontamination on templates: questions are found even with other numbers, names or units.

A word becomes a typed placeholder if it holds a digit (number), is a unit right after a number, or is capitalised and none
of the words that open sentences (name), whatever stands before it; other words lose case and outer punctuation. Windows of
`width` template words of every benchmark item (whole items if shorter) are hashed and joined with the windows of all
documents. Windows that are half placeholders or more are no evidence by their template; all windows also match by their
exact words (less case and outer punctuation), so a verbatim item is found whatever it is made of. Matches of an item are put
together along a diagonal of the text and those a few words beside it: `coverage` is the share of the item's words in matched
windows there, and the slots (words behind placeholders) must be consistent: one benchmark value always stands for one value
of the text, in at least `consistent` of the slots. A document is contaminated by an item covered to `least` or more at one
place.

Items of up to `block` bytes together are broadcast as a sorted index, and documents are only scanned. Larger benchmarks are
joined by the hash of their windows, shuffled; the pairs of document and item that share a window are then judged in the same
way. Null and empty texts match nothing, items without words too; texts are taken whole, however long; repeated rows of
either side are judged alike, an item that occurs twice in a text or under two ids is reported by each id once; columns of
other names pass through, whatever they are called.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.llm import common

#: Units that count as such right after a number.
UNITS = frozenset(b"mm cm m km ft mi mph kmh kg g mg lb lbs oz l ml gal s sec min h hr hours hour minutes minute seconds second days day weeks week months month years year km/h m/s % percent usd eur dollars dollar euros euro cents cent miles mile meters meter metres metre feet foot inches inch pounds pound grams gram liters liter litres litre degrees degree".split())
#: Words that open sentences and questions and are no names.
OPENERS = frozenset(b"a after all also an and any are as at be because before but by can compute could describe determine did do does during each every explain find for from given has have he her here his how i if in into is it its let list make many most my name no not of on one or our over she should show since so solve some such suppose than that the their then there these they this those to two under until us we were what when where which while who whom whose why will with would write you your".split())
NUMBER, NAME, UNIT = 1, 2, 3
#: Low bits of a word's code: its kind, and what it does to the words after it.
KIND_NUMBER, CAPITAL, IS_UNIT = 1, 2, 4
OUTER = b".,;:!?\"'()[]{}<>|*_`"
DIGIT = re.compile(rb"[0-9]")
SLOT_HASH = np.array([0, 0x9E37, 0x79B9, 0x7F4A], np.uint64)
#: Keeps hashes of exact words apart from those of templates.
EXACT = np.uint64(0x5851F42D4C957F2D)


class WordCodes(dict):
    """word -> hash of its plain form with four flag bits; forgets everything when it gets too large."""

    room = 500_000

    def __missing__(self, w: bytes) -> int:
        if len(self) >= self.room:
            self.clear()
        core = w.strip(OUTER)
        low = core.translate(common.LOWER)
        flags = KIND_NUMBER if DIGIT.search(core) else CAPITAL if core[:1].isupper() and low not in OPENERS else 0
        if low in UNITS:
            flags |= IS_UNIT
        code = self[w] = (xxhash.xxh64_intdigest(low, 7) >> 5 << 4) | flags
        return code


def coded(words: list[bytes], codes: WordCodes) -> np.ndarray:
    return np.fromiter(map(codes.__getitem__, words), np.int64, len(words))


def template(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(template hashes, placeholder kinds; 0 for plain words) of word codes."""
    number = (c & KIND_NUMBER) != 0
    after_number = np.zeros(len(c), bool)
    after_number[1:] = number[:-1]
    kind = np.zeros(len(c), np.int8)
    kind[(c & CAPITAL) != 0] = NAME
    kind[((c & IS_UNIT) != 0) & after_number] = UNIT
    kind[number] = NUMBER
    return np.where(kind > 0, SLOT_HASH[kind], exact(c)), kind


def exact(c: np.ndarray) -> np.ndarray:
    """Hashes of the words themselves, placeholders or not."""
    return (c >> 4).astype(np.uint64)


def item_windows(words: list[bytes], codes: WordCodes, width: int):
    """(size, [(hash, place) arrays of template and of exact windows], kinds) of an item with words."""
    c = coded(words, codes)
    t, kind = template(c)
    w = min(width, len(words))
    good = np.nonzero(2 * np.convolve(kind == 0, np.ones(w, int), "valid") > w)[0]
    plain = exact(c) ^ EXACT
    return w, [(common.rolled(t, w)[good], good), (common.rolled(plain, w), np.arange(len(words) - w + 1))], kind


class Windows:
    """Hashes of (hashes, item, places, size) parts, sorted, with their items and places."""

    def __init__(self, parts):
        none = np.empty(0, np.int64)
        columns = [(h, np.full(len(at), n), at, np.full(len(at), w)) for h, n, at, w in parts]
        h, item, at, size = (np.concatenate(x) for x in zip(*columns)) if columns else (none,) * 4
        order = np.argsort(h, kind="stable")
        self.hash, self.item, self.at, self.size = h[order].astype(np.uint64), item[order], at[order], size[order]
        self.sizes = sorted(set(size.tolist()))

    def hits(self, t: np.ndarray, found: dict) -> None:
        """Adds (place in the item, place in the text, size) of the windows of a text to its items' lists."""
        for w in self.sizes:
            h = common.rolled(t, w)
            k = np.searchsorted(self.hash, h)
            k[k == len(self.hash)] = 0
            for p in np.nonzero(self.hash[k] == h)[0].tolist():
                e = int(k[p])
                while e < len(self.hash) and self.hash[e] == h[p]:
                    if self.size[e] == w:
                        found.setdefault(int(self.item[e]), []).append((int(self.at[e]), p, w))
                    e += 1


def alignments(hits: list[tuple[int, int, int]], length: int):
    """Item place -> text place: per diagonal its own places and, for the rest, those of the nearest diagonals beside it."""
    diagonals: dict[int, set[int]] = {}
    for at, p, w in hits:
        diagonals.setdefault(p - at, set()).update(range(at, at + w))
    order, beside = sorted(diagonals), 4 + length // 10
    for main in order:
        near = order[bisect_left(order, main - beside) : bisect_right(order, main + beside)]
        one: dict[int, int] = {}
        for d in sorted(near, key=lambda d: abs(d - main)):
            for a in diagonals[d]:
                one.setdefault(a, a + d)
        yield one


class Index:
    """The windows of items, by template and by exact words."""

    def __init__(self, items: list[tuple[int, bytes]], width: int):
        codes = WordCodes()
        self.words = [body.split() for _, body in items]
        self.ids = [i for i, _ in items]
        self.kinds, parts = [], []
        for n, words in enumerate(self.words):
            if not words:
                self.kinds.append(None)
                continue
            w, both, kind = item_windows(words, codes, width)
            self.kinds.append(kind)
            parts += [(h, n, at, w) for h, at in both]
        self.windows = Windows(parts)

    def matches(self, body: bytes, codes: WordCodes, least: float, consistent: float):
        """[(item id, coverage)] that contaminate the text."""
        words = body.split()
        found: dict[int, list[tuple[int, int, int]]] = {}
        if words and len(self.windows.hash):
            c = coded(words, codes)
            self.windows.hits(template(c)[0], found)
            self.windows.hits(exact(c) ^ EXACT, found)
        out = []
        for n, hits in found.items():
            item = self.words[n]
            for aligned in alignments(hits, len(item)):
                coverage = len(aligned) / len(item)
                if coverage < least:
                    continue
                slots = [(item[a].strip(OUTER), words[p].strip(OUTER)) for a, p in aligned.items() if self.kinds[n][a]]
                meaning: dict[bytes, bytes] = {}
                agreed = sum(meaning.setdefault(a, b) == b for a, b in slots)
                if agreed >= consistent * len(slots):
                    out.append((self.ids[n], coverage))
                    break
        return out


def shared_windows(rows: DataFrame, items: DataFrame, width: int) -> DataFrame:
    """Distinct (_mc_row, item_id) that have a window in common, joined by hash. rows: _mc_row, _mc_body."""
    sizes = sorted({min(width, r[0]) for r in items.select(F.size(F.filter(F.split(F.col("body").cast("string"), common.BLANK + "+"), lambda w: w != "")).alias("n")).where("n > 0").select(F.least("n", F.lit(width))).distinct().collect()})

    def of_items(batches):
        codes = WordCodes()
        for b in batches:
            keys, ids = [], []
            for i, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                words = body.split()
                if words:
                    both = item_windows(words, codes, width)[1]
                    keys += [h for h, _ in both]
                    ids += [np.full(len(h), i) for h, _ in both]
            keys, ids = (np.concatenate(x) if x else np.empty(0, np.int64) for x in (keys, ids))
            yield pa.RecordBatch.from_arrays([pa.array(keys.astype(np.uint64).view(np.int64)), pa.array(ids)], names=["h", "item_id"])

    def of_rows(batches):
        codes = WordCodes()
        for b in batches:
            for lo in range(0, b.num_rows, 200):
                part = b.slice(lo, 200)
                keys, ids = [np.empty(0, np.uint64)], [np.empty(0, np.int64)]
                for i, body in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    c = coded(body.split(), codes)
                    t = template(c)[0]
                    h = np.unique(np.concatenate([common.rolled(x, w) for w in sizes for x in (t, exact(c) ^ EXACT)] or keys))
                    keys.append(h)
                    ids.append(np.full(len(h), i))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys).view(np.int64)), pa.array(np.concatenate(ids))], names=["h", "_mc_row"])

    keys = items.mapInArrow(of_items, "h long, item_id long").distinct()
    return rows.select("_mc_row", "_mc_body").mapInArrow(of_rows, "h long, _mc_row long").join(keys, "h").select("_mc_row", "item_id").distinct()


def leaks(docs: DataFrame, benchmark: DataFrame, *keep: str, width: int = 8, least: float = 0.5, consistent: float = 0.8, block: int = 64_000_000) -> DataFrame:
    """The columns named in keep, with `_mc_items` (ids, ascending) and `_mc_coverage` (the largest; 0 if none)."""
    spark = docs.sparkSession
    common.prepare(spark)
    items = benchmark.where("text is not null and item_id is not null").select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("binary").alias("body")).distinct()
    total = items.agg(F.coalesce(F.sum(F.length("body")), F.lit(0))).first()[0]
    body = F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("_mc_body")
    if total > block:
        rows = common.written(docs.select(*keep, body, F.monotonically_increasing_id().alias("_mc_row")), "leak-rows")
        pairs = shared_windows(rows, items, width)

        def judge(batches):
            codes = WordCodes()
            for b in batches:
                got = [Index([(i, item)], width).matches(text, codes, least, consistent) for text, i, item in zip(*(c.to_pylist() for c in b.columns[1:]))]
                hit = pa.array([bool(g) for g in got], pa.bool_())
                part = pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array([g[0][1] if g else 0.0 for g in got], pa.float64())], names=["_mc_row", "item_id", "coverage"])
                yield part.filter(hit)

        both = rows.select("_mc_row", "_mc_body").join(pairs, "_mc_row").join(items, "item_id").select("_mc_row", "_mc_body", "item_id", "body")
        found = both.mapInArrow(judge, "_mc_row long, item_id long, coverage double").groupBy("_mc_row").agg(F.sort_array(F.collect_set("item_id")).alias("_mc_items"), F.max("coverage").alias("_mc_coverage"))
        out = rows.drop("_mc_body").join(found, "_mc_row", "left")
        return out.select(*keep, F.coalesce("_mc_items", F.array().cast("array<bigint>")).alias("_mc_items"), F.coalesce("_mc_coverage", F.lit(0.0)).alias("_mc_coverage"))
    sent = spark.sparkContext.broadcast(Index(sorted((r[0], bytes(r[1])) for r in items.collect()), width))

    def run(batches):
        index, codes = sent.value, WordCodes()
        for b in batches:
            got = [index.matches(text, codes, least, consistent) for text in b.column(0).to_pylist()]
            ids = pa.array([sorted({i for i, _ in g}) for g in got], pa.list_(pa.int64()))
            best = pa.array([max((c for _, c in g), default=0.0) for g in got], pa.float64())
            yield pa.RecordBatch.from_arrays([*b.columns[1:], ids, best], names=[*keep, "_mc_items", "_mc_coverage"])

    fields = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keep)
    return docs.select(body, *keep).mapInArrow(run, f"{fields}, _mc_items array<bigint>, _mc_coverage double")


def decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, contaminated, item_ids and coverage of every document."""
    out = leaks(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"), "doc_id")
    return out.select("doc_id", (F.size("_mc_items") > 0).alias("contaminated"), F.col("_mc_items").alias("item_ids"), F.round("_mc_coverage", 6).alias("coverage"))


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents that hold a benchmark item go."""
    out = leaks(docs, common.table(spark, sf_dir, "benchmark"), *docs.columns)
    return out.where(F.size("_mc_items") == 0).select(*docs.columns)
