"""Exact substring dedup: every byte inside a run of `least` bytes that also starts earlier goes.

Equal runs must meet in one task without shuffling all suffixes. In every window of `least` bytes the least hash of the
`seed`-byte strings inside it (leftmost of equals) is its anchor; equal windows have the same anchor string at the same
place. Neighbouring windows with one anchor form a stretch, so a text is cut into few stretches and each window is in
exactly one. Stretches meet by anchor:

* a stretch equal to an earlier one is covered whole (first within a batch, then across all; no suffixes needed);
* different stretches with the same anchor string may share windows. A window holds the anchor string and `least - SEED`
  more bytes before and behind it, so those of up to half as many bytes before it agree behind it, the others before it: the
  stretches' bytes go to two groups, by the anchor string and the half that must agree (the core), without what their windows
  cannot reach. Each group is sorted by the Lyndon-prefix suffix construction, the core as one symbol; windows that are
  neighbours in suffix order and agree in all their symbols are one class, of which all but the earliest are covered.
  Groups over `hot` pieces are dealt out again in two with longer cores, and so on, until they are small or a piece is one
  window; so no task holds an unbounded group and none is settled otherwise.

"Earlier" is by id, then place; rows that repeat an id with another text are ordered by text hash and count as one document
with a gap between them, identical rows are one place. A null text is empty, a null id comes before all others. Texts under
`least` bytes never match; longer ones are taken whole, in chunks of bounded memory. Other columns are ignored, whatever they
are called.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from meshcut.llm import common
from meshcut.llm.lyndon import suffix_order

SEED = 32
CHUNK = 1 << 19
ROW = 1 << 40
PLACES = "pk long, h long, c long, id long, at long, n int, lead int, known boolean"
PLACE_NAMES = [x.split()[0] for x in PLACES.split(", ")]


def seed_hashes(b: np.ndarray) -> np.ndarray:
    """Mixed hashes of all SEED-byte strings, their low 20 bits zero."""
    h = b.astype(np.uint64) + np.uint64(0x9E3779B1)
    base = np.uint64(0xD6E8FEB86659FD93)
    with np.errstate(over="ignore"):
        step, width = base, 1
        while width < SEED:
            h = h[:-width] * step + h[width:]
            step, width = step * step, 2 * width
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xFF51AFD7ED558CCD)
        h ^= h >> np.uint64(29)
    return h & ~np.uint64(0xFFFFF)


def window_min(x: np.ndarray, width: int) -> np.ndarray:
    m, have = x, 1
    while 2 * have <= width:
        m = np.minimum(m[:-have], m[have:])
        have *= 2
    rest = width - have
    return np.minimum(m[: len(m) - rest], m[rest:]) if rest else m


def stretches(body: bytes, least: int):
    """(anchor hash, first byte, length, bytes before the anchor string) of each stretch."""
    b = np.frombuffer(body, np.uint8)
    windows = len(b) - least + 1
    out = []
    for lo in range(0, windows, CHUNK):
        part = b[lo : min(lo + CHUNK, windows) + least - 1]
        h = seed_hashes(part) | np.arange(len(part) - SEED + 1, dtype=np.uint64)
        m = window_min(h, least - SEED + 1)
        edge = np.append(0, np.nonzero(m[1:] != m[:-1])[0] + 1)
        size = np.diff(np.append(edge, len(m)))
        anchor = (m[edge] & np.uint64(0xFFFFF)).astype(np.int64)
        out.append(((m[edge] >> np.uint64(20)).astype(np.int64), edge + lo, size + least - 1, anchor - edge))
    if not out:
        return None
    return tuple(np.concatenate(x) for x in zip(*out))


def keyed(docs: DataFrame, *more) -> DataFrame:
    """_id, _row (rank of the text among those of its id), _body and more."""
    rows = common.doc_rows(docs, *more, common.text_hash().alias("_th"))
    ids = rows.select("_id", "_th").distinct()
    twice = ids.groupBy("_id").count().where("count > 1").select("_id")
    if not twice.limit(1).count():
        return rows.withColumn("_row", F.lit(0).cast("long")).drop("_th")
    rank = ids.join(twice, "_id").select("_id", "_th", (F.row_number().over(Window.partitionBy("_id").orderBy("_th")) - 1).cast("long").alias("_row"))
    return rows.join(rank, ["_id", "_th"], "left").withColumn("_row", F.coalesce("_row", F.lit(0).cast("long"))).drop("_th")


def _batch(columns, names):
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=names)


def find_stretches(rows: DataFrame, least: int) -> DataFrame:
    def run(batches):
        for b in batches:
            held, size = [], 0
            for i, r, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                got = stretches(body, least)
                if got is None:
                    continue
                h, s, n, lead = got
                digest = xxhash.xxh3_64_digest
                c = np.frombuffer(b"".join([digest(body[x : x + y]) for x, y in zip(s.tolist(), n.tolist())]), ">u8").astype(np.int64)
                held.append((h, c, np.full(len(h), i), s + r * ROW, n, lead))
                size += len(h)
                if size > 400_000:
                    yield local(held)
                    held, size = [], 0
            if held:
                yield local(held)

    def local(held):
        h, c, i, s, n, lead = (np.concatenate(x) for x in zip(*held))
        order = np.lexsort((s, i, c, h))
        h, c, i, s, n, lead = (x[order] for x in (h, c, i, s, n, lead))
        same = np.concatenate([[False], (h[1:] == h[:-1]) & (c[1:] == c[:-1])])
        # an identical place (repeated rows) is not later than itself
        first = np.maximum.accumulate(np.where(same, 0, np.arange(len(h))))
        known = same & ((i != i[first]) | (s != s[first]))
        spread = np.where(known, c * np.int64(31) + s, h)
        return _batch((spread, h, c, i, s, n.astype(np.int32), lead.astype(np.int32), known), PLACE_NAMES)

    return rows.select("_id", "_row", "_body").mapInArrow(run, PLACES)


FOUND = "kind int, h long, id long, at long, n int, lead int"
FOUND_NAMES = [x.split()[0] for x in FOUND.split(", ")]
FOUND_TYPES = [{"int": np.int32, "long": np.int64}[x.split()[1]] for x in FOUND.split(", ")]


def meet(batches):
    """Rows by pk, h, c, id, at. Kind 0: covered stretches. Kind 1: first stretches whose anchor has other contents."""
    last = None  # h, c, id, at of the current content's first; whether its anchor is already known to have others
    pending = None
    for b in batches:
        pk, h, c, i, s, n, lead, known = (b.column(k).to_numpy(zero_copy_only=False) for k in range(8))
        own = ~known
        covered = [x[known] for x in (h, i, s, n, lead)]
        h, c, i, s, n, lead = (x[own] for x in (h, c, i, s, n, lead))
        if len(h):
            new_h = np.concatenate([[last is None or last[0] != h[0]], h[1:] != h[:-1]])
            new_c = new_h | np.concatenate([[last is None or last[1] != c[0]], c[1:] != c[:-1]])
            first = np.maximum.accumulate(np.where(new_c, np.arange(len(h)), -1))
            fi = np.where(first >= 0, i[np.maximum(first, 0)], last[2] if last else 0)
            fs = np.where(first >= 0, s[np.maximum(first, 0)], last[3] if last else 0)
            later = ~new_c & ((i != fi) | (s != fs))
            covered = [np.concatenate([x, y[later]]) for x, y in zip(covered, (h, i, s, n, lead))]
            firsts = np.nonzero(new_c)[0]
            # a first has company if the first before or after it has the same anchor
            fh = h[firsts]
            prev = np.concatenate([[last is not None and len(fh) > 0 and last[0] == fh[0]], fh[1:] == fh[:-1]]) if len(fh) else np.empty(0, bool)
            if len(fh):
                if pending is not None:
                    if prev[0]:
                        yield _batch([np.array([x], t) for x, t in zip((1, *pending), FOUND_TYPES)], FOUND_NAMES)
                    pending = None
                after = np.concatenate([fh[1:] == fh[:-1], [False]])
                out = firsts[prev | after]
                if len(out):
                    yield _batch((np.ones(len(out), np.int32), h[out], i[out], s[out], n[out], lead[out]), FOUND_NAMES)
                if not (prev[-1] or after[-1]):
                    z = firsts[-1]
                    pending = (int(h[z]), int(i[z]), int(s[z]), int(n[z]), int(lead[z]))
            last = (h[-1], c[-1], fi[-1], fs[-1])
        if len(covered[0]):
            yield _batch((np.zeros(len(covered[0]), np.int32), *covered), FOUND_NAMES)


def piece(body: bytes, c0: int, a: int, b: int, least: int):
    """The part of a stretch that windows with a to b bytes before c0 use: (first byte, core's place in it, bytes).

    Its core, least - (b - a) bytes long, is in all those windows. None if it has no such window.
    """
    first, last = max(0, c0 - b), min(len(body), c0 - a + least)
    if c0 < a or c0 - b + least > len(body) or last - first < least:
        return None
    return first, c0 - a - first, body[first:last]


def later_windows(groups, width: int, least: int):
    """Covered runs (id, at, n) of groups [[(id, at, core's place, bytes)]] of pieces, by suffix order.

    A core stands in the text as one symbol, so windows are strings of width + 1 symbols that hold one. Pieces of equal
    bytes in a group stand there once: all but the earliest are covered.
    """
    out, symbols, where, cores = [], [], [], {}
    for group in groups:
        places: dict[tuple[int, bytes], tuple[int, int]] = {}
        for i, s, c, body in group:
            one = places.get((c, body))
            if one is None:
                places[c, body] = i, s
            elif one != (i, s):
                from_, upto = max(0, c - width), min(c, len(body) - least)
                out.append((i, s + from_, upto - from_ + least))
        if len(places) < 2:
            continue
        for (c, body), (i, s) in places.items():
            core = cores.setdefault(body[c : c + least - width], 257 + len(cores))
            symbols += [x + 1 for x in body[:c]]
            symbols.append(core)
            symbols += [x + 1 for x in body[c + least - width :]]
            symbols.append(0)
            fit = min(c, len(body) - least) + 1
            where += [(i, s + k) for k in range(fit)] + [None] * (len(body) - least + width + 2 - fit)
    text = "".join(map(chr, symbols))
    found, held, key = [], [], None
    for p in suffix_order(symbols):
        if where[p] is None:
            continue
        now = text[p : p + width + 1]
        if now != key:
            if len(held) > 1:
                one = min(held)
                found += [x for x in held if x != one]
            held, key = [], now
        held.append(where[p])
    if len(held) > 1:
        one = min(held)
        found += [x for x in held if x != one]
    for i, s in sorted(set(found)):
        if out and out[-1][0] == i and out[-1][1] <= s <= out[-1][1] + out[-1][2]:
            out[-1] = i, out[-1][1], s + least - out[-1][1]
        else:
            out.append((i, s, least))
    return out


PIECES = "key long, id long, at long, core int, body binary"
PIECE_NAMES = [x.split()[0] for x in PIECES.split(", ")]
SPANS = "n int, " + PIECES
SPAN_NAMES = ["n", *PIECE_NAMES]


def _spans(found):
    ids, ats, ns = zip(*found) if found else ((), (), ())
    n = len(ids)
    return _batch((pa.array(ns, pa.int32()), pa.nulls(n, pa.int64()), pa.array(ids, pa.int64()), pa.array(ats, pa.int64()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary())), SPAN_NAMES)


def sort_groups(width: int, least: int, hot: int):
    """Pieces by key, core, body, id, at. Gives covered runs, or the pieces of hot groups (n is null).

    Of equal pieces in a group only the earliest is sorted or dealt on; the others are covered. So a group is hot by its
    different pieces, and copies of one never multiply with the rounds.
    """

    def run(batches):
        held, key, spilled = [], None, False
        joint, size, later = [], 0, []
        for b in batches:
            for k, i, s, c, body in zip(*(b.column(x).to_pylist() for x in range(5))):
                if k != key:
                    if spilled and held:
                        yield hot_rows(key, held)
                    elif len(held) > 1:
                        joint.append(held)
                        size += len(held)
                    held, key, spilled, now = [], k, False, None
                    if size > 300:
                        yield _spans(later_windows(joint, width, least))
                        joint, size = [], 0
                if now == (c, body):
                    if place != (i, s):
                        place = i, s
                        from_, upto = max(0, c - width), min(c, len(body) - least)
                        later.append((i, s + from_, upto - from_ + least))
                        if len(later) > 5000:
                            yield _spans(later)
                            later = []
                    continue
                now, place = (c, body), (i, s)
                held.append((i, s, c, body))
                if len(held) > hot or (spilled and len(held) > 500):
                    yield hot_rows(key, held)
                    held, spilled = [], True
            if spilled and held:
                yield hot_rows(key, held)
                held = []
        if not spilled and len(held) > 1:
            joint.append(held)
        if joint:
            yield _spans(later_windows(joint, width, least))
        if later:
            yield _spans(later)

    def hot_rows(k, held):
        ids, ats, cores, bodies = zip(*held)
        return _batch((pa.nulls(len(ids), pa.int32()), pa.array([k] * len(ids), pa.int64()), pa.array(ids, pa.int64()), pa.array(ats, pa.int64()), pa.array(cores, pa.int32()), pa.array(bodies, pa.binary())), SPAN_NAMES)

    return run


def dealt(columns):
    key, i, s, c, body = zip(*columns) if columns else ((),) * 5
    return _batch((pa.array(key, pa.int64()), pa.array(i, pa.int64()), pa.array(s, pa.int64()), pa.array(c, pa.int32()), pa.array(body, pa.binary())), PIECE_NAMES)


def halves(width: int, half: int, least: int):
    """The pieces of a hot group again, those of windows with up to `half` bytes before the core apart from those with more."""

    def run(batches):
        for batch in batches:
            out = []
            for k, i, s, c, body in zip(*(batch.column(x).to_pylist() for x in range(5))):
                for a in (0, width - half):
                    got = piece(body, c, a, a + half, least)
                    if got is not None:
                        at, core, part = got
                        out.append((deal(k.to_bytes(8, "little", signed=True), a, part[core : core + least - half]), i, s + at, core, part))
            yield dealt(out)

    return run


def deal(under: bytes, a: int, core: bytes) -> int:
    return xxhash.xxh3_64_intdigest(under + a.to_bytes(2, "little") + core) - 2**63


def covered_runs(rows: DataFrame, least: int = 100, hot: int = 1000) -> DataFrame:
    """(id, at, n): byte runs to remove; they may touch and overlap. at counts from ROW * _row."""
    met = find_stretches(rows, least).repartition("pk").sortWithinPartitions("pk", "h", "c", "id", "at").mapInArrow(meet, FOUND)
    met = common.written(met, "stretches")
    out = met.where("kind = 0").select("id", "at", "n")
    wanted = met.where("kind = 1").groupBy(F.col("id").alias("_id"), F.shiftright("at", 40).alias("_row")).agg(F.collect_list(F.struct("h", (F.col("at") % ROW).alias("at"), "n", "lead")).alias("_w"))
    # windows with up to `width` bytes before the anchor string, and those with more
    width = (least - SEED) // 2

    def fetch(batches):
        for batch in batches:
            out = []
            for i, r, body, want in zip(*(batch.column(c).to_pylist() for c in range(4))):
                for x in want:
                    got, under = body[x["at"] : x["at"] + x["n"]], x["h"].to_bytes(8, "little", signed=True)
                    for a in (0, least - SEED - width):
                        part = piece(got, x["lead"], a, a + width, least)
                        if part is not None:
                            at, core, piece_ = part
                            out.append((deal(under, a, piece_[core : core + least - width]), i, x["at"] + at + r * ROW, core, piece_))
            yield dealt(out)

    pieces = rows.join(wanted, ["_id", "_row"]).select("_id", "_row", "_body", "_w").mapInArrow(fetch, PIECES)
    while True:
        found = pieces.repartition("key").sortWithinPartitions("key", "core", "body", "id", "at").mapInArrow(sort_groups(width, least, hot), SPANS)
        found = common.written(found, "suffix-groups")
        out = out.unionByName(found.where("n is not null").select("id", "at", "n"))
        rest = found.where("n is null").drop("n")
        if not rest.limit(1).count():
            return out
        if width == 0:
            # a piece is one window: all but the first of equal ones are covered
            place = F.struct("id", "at")
            first = rest.groupBy("body").agg(F.min(place).alias("f"), F.max(place).alias("z")).where("f <> z").select("body", "f")
            return out.unionByName(rest.join(first, "body").where(place != F.col("f")).select("id", "at", F.lit(least).cast("int").alias("n")))
        half = (width + 1) // 2 if width > 1 else 0
        pieces = rest.select(*PIECE_NAMES).mapInArrow(halves(width, half, least), PIECES)
        width = half


def trimmed(docs: DataFrame, least: int = 100, hot: int = 1000) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (the bytes left), removed (array of start and end)."""
    common.prepare(docs.sparkSession)
    rows = keyed(docs)
    runs = covered_runs(rows, least, hot).groupBy(F.col("id").alias("_id"), F.shiftright("at", 40).alias("_row")).agg(F.collect_list(F.struct((F.col("at") % ROW).alias("a"), "n")).alias("_runs"))

    def cut(batches):
        for b in batches:
            n, gone, spans, kept, removed = [], [], [], [], []
            for body, runs in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                merged: list[list[int]] = []
                for a, z in sorted((r["a"], r["a"] + r["n"]) for r in runs or ()):
                    if merged and a <= merged[-1][1]:
                        merged[-1][1] = max(merged[-1][1], z)
                    else:
                        merged.append([a, z])
                left, at = [], 0
                for a, z in merged:
                    left.append(body[at:a])
                    at = z
                left.append(body[at:])
                n.append(len(body))
                gone.append(sum(z - a for a, z in merged))
                spans.append(len(merged))
                kept.append(b"".join(left))
                removed.append(merged)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(spans, pa.int64()), pa.array(kept, pa.binary()), pa.array(removed, pa.list_(pa.list_(pa.int64())))], names=["_id", "n_bytes", "n_removed", "n_spans", "kept", "removed"])

    joined = rows.join(runs, ["_id", "_row"], "left").select("_id", "_body", "_runs")
    out = joined.mapInArrow(cut, "_id long, n_bytes long, n_removed long, n_spans long, kept binary, removed array<array<bigint>>")
    return out.select(common.public_id("_id").alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept", "removed")


def suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = trimmed(common.table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
