"""Packing along a space-filling curve: neighbours in a hashed vector space share training sequences.

A document's vector is the mean of three hash bytes of all its byte 4-grams (texts under four bytes are filled up with zeros); the curve index of its cell orders
the documents (ties by id), one range shuffle deals them out, and each partition lays its documents end to end and cuts the
stream every `length` tokens. A partition's last, partial sequence is cut into powers of two, which need no padding, so no
token is padding at all.

Tokens are those of a `tokenizers` file for the whole text, then one end id. Words are encoded one by one and kept in a
bounded cache: the file's pre-tokenizer never joins text across ASCII white space. Words of Latin letters with a tail of
commas or stops go to the file's model directly, all others through its whole pipeline.

A null text is empty (its only token is the end id), a null doc_id keeps its row; rows that repeat an id are packed as rows
of their own. Longer texts than a sequence are cut; every token is in exactly one piece.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from meshcut.llm import common

PLAIN = re.compile("[A-Za-zÀ-ÖØ-öø-ÿ]+")
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_ENCODERS: dict = {}


def byte_letters() -> dict[int, str]:
    """Translation of Latin-1 letters to the printable stand-ins of their UTF-8 bytes in byte-level vocabularies."""
    printable = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(printable)]
    stand_in = {b: chr(b) for b in printable} | {b: chr(256 + i) for i, b in enumerate(rest)}
    return {c: "".join(stand_in[b] for b in chr(c).encode()) for c in range(0xC0, 0x100)}


class WordEncoder:
    """Bytes of the ids (little-endian, 32 bits) of white-space separated words."""

    def __init__(self, path: str, room: int = 400_000):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.model = self.whole.model
        self.letters = byte_letters()
        self.room = room
        self.known: dict[bytes, bytes] = {}
        self.parts: dict[str, bytes] = {}

    def part(self, text: str) -> bytes:
        got = self.parts.get(text)
        if got is None:
            if len(self.parts) >= self.room:
                self.parts.clear()
            got = self.parts[text] = np.array([x.id for x in self.model.tokenize(text)], "<u4").tobytes()
        return got

    def word(self, w: bytes) -> bytes:
        text = w.decode("utf-8", "replace")
        head = text.rstrip(",.")
        if PLAIN.fullmatch(head):
            got = self.part(head.lower().translate(self.letters))
            if len(head) < len(text):
                got += self.part(text[len(head) :])
        else:
            got = np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        if len(self.known) >= self.room:
            self.known.clear()
        self.known[w] = got
        return got

    def encode(self, body: bytes) -> bytes:
        get, miss = self.known.get, self.word
        return b"".join([get(w) or miss(w) for w in body.split()])


def encoder(path: str) -> WordEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = WordEncoder(path)
    return _ENCODERS[path]


def document_cells(bodies: list[bytes], bits: int = 10) -> np.ndarray:
    """(n, 3) cells of the hashed document vectors."""
    out = np.zeros((len(bodies), 3), np.uint32)
    top = (1 << bits) - 1
    for i, body in enumerate(bodies):
        b = np.frombuffer(body.ljust(4, b"\0"), np.uint8)
        h = np.concatenate([b[o : o + (len(b) - o) // 4 * 4].view("<u4") for o in range(4)])
        h = h * np.uint32(0x9E3779B1)
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x85EBCA77)
        # column sums of whole arrays: a mean over rows of three bytes costs several times as much
        v = np.array([(h >> np.uint32(k) & np.uint32(255)).sum(dtype=np.int64) for k in (8, 16, 24)]) / len(h)
        out[i] = np.clip((0.5 + (v - 127.5) / 40) * top, 0, top)
    return out


def hilbert_index(cells: np.ndarray, bits: int = 10) -> np.ndarray:
    """Positions on the Hilbert curve of (n, d) cells, by undoing excess work bit by bit and a Gray decode."""
    x = [c.astype(np.uint32).copy() for c in cells.T]
    d = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = np.uint32(q - 1)
        for i in range(d):
            on = (x[i] & np.uint32(q)) != 0
            t = np.where(on, 0, (x[0] ^ x[i]) & p).astype(np.uint32)
            x[0] = np.where(on, x[0] ^ p, x[0] ^ t)
            x[i] = x[i] ^ t if i else x[i]
        q >>= 1
    for i in range(1, d):
        x[i] = x[i] ^ x[i - 1]
    t = np.zeros(len(cells), np.uint32)
    q = 1 << (bits - 1)
    while q > 1:
        t = np.where((x[d - 1] & np.uint32(q)) != 0, t ^ np.uint32(q - 1), t)
        q >>= 1
    x = [c ^ t for c in x]
    key = np.zeros(len(cells), np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(d):
            key = (key << 1) | ((x[i] >> np.uint32(b)) & np.uint32(1)).astype(np.int64)
    return key


@F.arrow_udf(T.LongType())
def curve_key(body: pa.Array) -> pa.Array:
    return pa.array(hilbert_index(document_cells(body.to_pylist())))


class Cutter:
    """Lays documents end to end and cuts the stream into sequences."""

    def __init__(self, length: int, first_id: int):
        self.length, self.next_id = length, first_id
        self.rows: list[tuple] = []
        self.open: list[tuple] = []
        self.used = 0

    def add(self, doc_id, ids: bytes) -> None:
        n = len(ids) // 4
        at = 0
        while at < n:
            take = min(n - at, self.length - self.used)
            self.open.append((doc_id, at, take, ids[4 * at : 4 * (at + take)], n))
            self.used += take
            at += take
            if self.used == self.length:
                self.close(self.length)

    def close(self, size: int) -> None:
        """Makes a sequence of the first `size` open tokens."""
        offset, left = 0, []
        for doc_id, start, n, ids, total in self.open:
            here = min(n, size - offset)
            if here:
                self.rows.append((doc_id, start, here, zlib.crc32(ids[: 4 * here]), total, self.next_id, offset))
                offset += here
            if here < n:
                left.append((doc_id, start + here, n - here, ids[4 * here :], total))
        self.open, self.used = left, self.used - size
        self.next_id += 1

    def finish(self) -> None:
        while self.used:
            self.close(1 << (self.used.bit_length() - 1))

    def batch(self) -> pa.RecordBatch:
        columns = list(zip(*self.rows)) or [()] * 7
        self.rows = []
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=[x.split()[0] for x in PIECES.split(", ")])


def pack(docs: DataFrame, vocabulary: str, length: int = 2048, end: int = 1) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    tail = np.array([end], "<u4").tobytes()

    def run(batches):
        enc = encoder(vocabulary)
        cut = Cutter(length, TaskContext.get().partitionId() << 40)
        for b in batches:
            for i, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                cut.add(None if i == common.NO_ID else i, enc.encode(body) + tail)
                if len(cut.rows) >= 20000:
                    yield cut.batch()
        cut.finish()
        yield cut.batch()

    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = common.doc_rows(docs).withColumn("_key", curve_key("_body"))
    rows = rows.repartitionByRange(parts, "_key", "_id").sortWithinPartitions("_key", "_id", F.xxhash64("_body"))
    return rows.select("_id", "_body").mapInArrow(run, PIECES)


def vocabulary_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(common.table(spark, sf_dir, "documents"), vocabulary_path())


def pack_kept(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Last pipeline stage: the pieces of the documents that are left."""
    common.prepare(spark)
    return pack(docs, vocabulary_path())
