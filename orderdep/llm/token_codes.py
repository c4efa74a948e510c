"""Token ids as directly addressable codes.

An id is split into chunks of ``CHUNK_BITS`` bits.  Level k holds the k-th chunk of every id that has one, a bitmap
that says which of them go on to the next level, and a directory with the number of set bits before each block of
the bitmap; so token i is read with one look into each level, and no block of tokens is ever decoded.

A segment is one binary image: header, document table and levels.  A folder of segments is a Parquet table with a
segment a row (``part``, ``seq``, ``local_start``, ``n_docs``, ``n_tokens``, ``image``), its parts and segments in
ascending order of document id; Parquet gives the atomic commit and works on any store that Spark writes.

Null and empty texts hold only the end id.  ``doc_id`` is an integer; rows without one come first, and rows with the
same id are ordered by a hash of their text and then as read, so that many of them are dealt over several tasks.
Other columns are not read.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import let_go, own, small_batches, stored
from .tokens import encoder

CHUNK_BITS = 8
BLOCK_BITS = 512
SEGMENT_TOKENS = 1 << 20
#: Bytes of texts that a batch sent to a Python worker has before it is closed.
BATCH_BYTES = 4 << 20
_HEAD = struct.Struct("<4sHHQQ")
_LEVEL = struct.Struct("<QQQ")
_MAGIC = b"DACS"


def pack_segment(doc_ids: list[int | None], lengths: list[int], ids: np.ndarray) -> bytes:
    """A segment image of the concatenated ids of some documents."""
    have = np.array([d is not None for d in doc_ids], np.uint8)
    out = [np.array([d or 0 for d in doc_ids], "<i8").tobytes(), have.tobytes(), np.cumsum([0, *lengths]).astype("<u8").tobytes()]
    levels, rest = 0, ids.astype("<u4")
    while len(rest) or not levels:
        chunk, high = (rest & ((1 << CHUNK_BITS) - 1)).astype(np.uint8), rest >> CHUNK_BITS
        goes_on = high > 0
        bits = np.packbits(goes_on, bitorder="little")
        bits = np.concatenate([bits, np.zeros(-len(bits) % (BLOCK_BITS // 8), np.uint8)])
        ranks = np.concatenate([[0], np.cumsum(np.bitwise_count(bits).reshape(-1, BLOCK_BITS // 8).sum(1))]).astype("<u8")
        out.append(_LEVEL.pack(len(chunk), len(bits), len(ranks)) + chunk.tobytes() + bits.tobytes() + ranks.tobytes())
        rest, levels = high[goes_on], levels + 1
    return b"".join([_HEAD.pack(_MAGIC, levels, CHUNK_BITS, len(doc_ids), len(ids)), *out])


class Segment:
    """Reads single tokens, ranges and documents of a segment image."""

    def __init__(self, image: bytes):
        magic, n_levels, self.chunk_bits, n_docs, self.n_tokens = _HEAD.unpack_from(image)
        if magic != _MAGIC:
            raise ValueError("not a segment")
        at = _HEAD.size
        values = np.frombuffer(image, "<i8", n_docs, at)
        have = np.frombuffer(image, np.uint8, n_docs, at := at + 8 * n_docs)
        self.doc_ids = [v if h else None for v, h in zip(values.tolist(), have.tolist())]
        self.starts = np.frombuffer(image, "<u8", n_docs + 1, at := at + n_docs)
        at += 8 * (n_docs + 1)
        self.levels = []
        for _ in range(n_levels):
            n, n_bits, n_ranks = _LEVEL.unpack_from(image, at)
            at += _LEVEL.size
            chunk, bits = np.frombuffer(image, np.uint8, n, at), np.frombuffer(image, np.uint8, n_bits, at + n)
            self.levels.append((chunk, bits, np.frombuffer(image, "<u8", n_ranks, at + n + n_bits)))
            at += n + n_bits + 8 * n_ranks

    def _rank(self, level: int, i: int) -> int:
        _, bits, ranks = self.levels[level]
        block = i // BLOCK_BITS
        some = bits[block * (BLOCK_BITS // 8) : -(-i // 8)]
        inside = int(np.bitwise_count(some).sum(dtype=np.int64))
        if i % 8 and len(some):
            inside -= int(some[-1] >> (i % 8)).bit_count()
        return int(ranks[block]) + inside

    def token(self, i: int) -> int:
        if not 0 <= i < self.n_tokens:
            raise IndexError(i)
        value = shift = level = 0
        while True:
            chunk, bits, _ = self.levels[level]
            value |= int(chunk[i]) << shift
            if not bits[i // 8] >> (i % 8) & 1:
                return value
            i, level, shift = self._rank(level, i), level + 1, shift + self.chunk_bits

    def tokens(self, first: int, end: int, level: int = 0) -> np.ndarray:
        """Tokens first to end - 1, reading only their own chunks."""
        chunk, bits, _ = self.levels[level]
        value = chunk[first:end].astype("<u4")
        on = np.unpackbits(bits[first // 8 : -(-end // 8)], bitorder="little")[first % 8 : first % 8 + end - first].astype(bool)
        if on.any():
            a = self._rank(level, first)
            value[on] |= self.tokens(a, a + int(on.sum()), level + 1) << self.chunk_bits
        return value

    def document(self, k: int) -> np.ndarray:
        return self.tokens(int(self.starts[k]), int(self.starts[k + 1]))


SEGMENTS = "part long, seq long, local_start long, n_docs long, n_tokens long, image binary"


def encode_segments(docs: DataFrame, tokenizer_file: str, end_id: int, *, segment_tokens: int = SEGMENT_TOKENS) -> DataFrame:
    """Segments in ascending order of doc_id: one shuffle of the texts by ranges of ids."""
    tie = [F.xxhash64("text").alias(own("hash")), F.monotonically_increasing_id().alias(own("row"))]
    keys = ["doc_id", own("hash"), own("row")]
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *tie).repartitionByRange(*keys).sortWithinPartitions(*keys)
    end = np.array([end_id], "<u4").tobytes()

    def segments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part = encoder(tokenizer_file), TaskContext.get().partitionId()
        seq = start = held = 0
        names: list[int | None] = []
        parts: list[bytes] = []

        def flush() -> pa.RecordBatch:
            ids = np.frombuffer(b"".join(parts), "<u4")
            image = pack_segment(names, [len(p) // 4 for p in parts], ids)
            return pa.RecordBatch.from_pydict({"part": pa.array([part]), "seq": pa.array([seq]), "local_start": pa.array([start]), "n_docs": pa.array([len(names)]), "n_tokens": pa.array([len(ids)]), "image": pa.array([image], pa.binary())})

        for b in batches:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1)):
                ids = enc.encode(text.as_py()) + end
                names.append(doc_id)
                parts.append(ids)
                held += len(ids) // 4
                if held >= segment_tokens:
                    yield flush()
                    seq, start, held, names, parts = seq + 1, start + held, 0, [], []
        if names:
            yield flush()
        del parts
        let_go()

    return ordered.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(segments, SEGMENTS)


def with_starts(segments: DataFrame) -> DataFrame:
    """Adds ``start``, the tokens before each segment.  What is broadcast is one row for each part written."""
    totals = segments.groupBy("part").agg(F.sum("n_tokens").alias("total"))
    before = totals.select("part", (F.sum("total").over(Window.orderBy("part")) - F.col("total")).alias("before"))
    return segments.join(F.broadcast(before), "part").withColumn("start", F.col("before") + F.col("local_start"))


def document_digests(segments: DataFrame) -> DataFrame:
    """Per document, from the images alone: doc_id, start, n_tokens, ids_crc32."""

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for base, image in zip(b.column(0).to_pylist(), b.column(1)):
                s = Segment(image.as_py())
                ids = s.tokens(0, s.n_tokens).tobytes()
                at = (s.starts * 4).tolist()
                crc = [zlib.crc32(ids[x:y]) for x, y in zip(at, at[1:])]
                yield pa.RecordBatch.from_pydict({"doc_id": pa.array(s.doc_ids, pa.int64()), "start": pa.array(s.starts[:-1].astype(np.int64) + base), "n_tokens": pa.array(np.diff(s.starts.astype(np.int64))), "ids_crc32": pa.array(crc, pa.int64())})

    return with_starts(segments).select("start", "image").mapInArrow(digests, "doc_id long, start long, n_tokens long, ids_crc32 long")


def written(docs: DataFrame, tokenizer_file: str, end_id: int) -> DataFrame:
    """Segments written to the shared folder and opened again."""
    with small_batches(docs.sparkSession, size=BATCH_BYTES):
        return stored(encode_segments(docs, tokenizer_file, end_id), "token-codes", codec="none")
