"""Stupid-backoff scores of documents under the n-gram counts of all other documents.

Words: lower case (A-Z), cut at white space; every word and every n-gram up to ``order`` words counts.  With f(g) the
count of g in all documents less its count in the document itself, the word behind the context u is scored

    S(w | u) = f(u w) / f(u)        if f(u w) > 0
             = 0.4 * S(w | u')      otherwise, u' being u without its first word
    S(w)     = f(w) / F, or 0.4 / F where f(w) = 0          (F: words of all other documents, 1 at least)

u is what precedes w in the document, order - 1 words at most.  A document that stands in the corpus twice is thus
predicted by its copy; one that stands there alone backs off wherever it says something of its own.

Three tables, each dealt by hash:

1. Chunks: some documents as word numbers, with the 64-bit hashes of their different words.  A chunk's n-grams of all
   orders become one sorted list of different hashes with their counts, cut into buckets of the hash space; hashes get
   longer with the number of buckets, up to 64 bits.  An
   n-gram has one entry a chunk, however many documents hold it, so no n-gram is hot.
2. The count table: a bucket's task adds the counts of all chunks up and joins the totals back to each chunk's list.
3. A chunk's task joins the totals to its documents' own n-grams, subtracts their own counts, backs off and sums.

The lists travel as packed columns (differences of sorted hashes), since a row for each document and n-gram needs more
than the disk that the operator may use; README has the figures.  Nothing is sent to all tasks and nothing is cut off.

Null and empty texts have no words: score 0, mean null.  ``doc_id`` is an integer or null; rows with the same id are documents
of their own.  Other columns are not read.  Empty table: empty result.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored

ORDER = 3
BACKOFF = 0.4
#: Words after which a chunk is closed; a document is never cut.
CHUNK_WORDS = 1 << 21
#: n-grams of a bucket of the hash space, repeats included: what a task holds at once.
BUCKET_GRAMS = 1 << 22
#: Shuffle partitions of the lists; a task takes several buckets one after the other beyond it.
MOST_PARTS = 100_000
#: Numbers up to which a packed column is not compressed.
FEW = 32
#: Bits of an n-gram's hash inside its bucket: of the n-grams in a bucket one in some hundred million shares its hash.
BUCKET_BITS = 50
#: Different words whose hashes a worker remembers.
KNOWN_WORDS = 400_000
_HEAD, _SIZE = struct.Struct("<QB"), struct.Struct("<I")
_LOWER = bytes(b + 32 if 0x41 <= b <= 0x5A else b for b in range(256))
_A, _B, _C = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def words_of(text: bytes | None) -> list[bytes]:
    return text.translate(_LOWER).split() if text else []


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= KNOWN_WORDS:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def _pack(a: np.ndarray) -> bytes:
    """The bytes of each place by themselves, compressed: their number, which places are not all zero, and each with its size."""
    if len(a) <= FEW:
        return _HEAD.pack(len(a), 0) + a.tobytes()
    places = np.ascontiguousarray(a.view(np.uint8).reshape(-1, a.itemsize).T)
    used = [k for k in range(a.itemsize) if places[k].any()]
    out = [_HEAD.pack(len(a), sum(1 << k for k in used))]
    for k in used:
        raw = zstandard.compress(places[k], 1)
        out += [_SIZE.pack(len(raw)), raw]
    return b"".join(out)


def _unpack(raw: bytes, kind) -> np.ndarray:
    n, used = _HEAD.unpack_from(raw)
    at, size = _HEAD.size, np.dtype(kind).itemsize
    if n <= FEW:
        return np.frombuffer(raw, kind, n, at)
    places = np.zeros((size, n), np.uint8)
    for k in range(size):
        if used >> k & 1:
            (length,) = _SIZE.unpack_from(raw, at)
            at += _SIZE.size
            places[k] = np.frombuffer(zstandard.decompress(raw[at : at + length]), np.uint8)
            at += length
    return np.ascontiguousarray(places.T).view(kind).ravel()


def _pack_steps(a: np.ndarray) -> bytes:
    """Hashes in ascending stretches, as differences."""
    return _pack(np.diff(a, prepend=np.uint64(0)))


def _unpack_steps(raw: bytes) -> np.ndarray:
    return np.cumsum(_unpack(raw, np.uint64), dtype=np.uint64)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _B
    x = (x ^ (x >> np.uint64(27))) * _C
    return x ^ (x >> np.uint64(31))


def gram_hashes(hashes: np.ndarray, place: np.ndarray, order: int) -> list[np.ndarray]:
    """Per order the hash of the n-gram that ends at each word; ``place``: words before it in its document.

    Where a document has too few words before, the entry is that of the longest n-gram there is.
    """
    out = [_mixed(hashes + _A)]
    for n in range(1, order):
        longer = out[-1].copy()
        at = np.flatnonzero(place >= n)
        longer[at] = _mixed(out[-1][at - 1] * _A + hashes[at] + np.uint64(n))
        out.append(longer)
    return out


def _places(sizes: np.ndarray) -> np.ndarray:
    starts = np.cumsum(sizes) - sizes
    return np.arange(int(sizes.sum())) - np.repeat(starts, sizes)


CHUNKS = "chunk long, n_words long, doc_ids binary, have binary, sizes binary, words binary, numbers binary"


def chunks(docs: DataFrame, chunk_words: int = CHUNK_WORDS) -> DataFrame:
    """Documents as numbers into the hashes of the different words of their chunk."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, chunk = _Hashes(), TaskContext.get().partitionId() << 32
        ids: list[int | None] = []
        hashes: list[np.ndarray] = []
        held = 0

        def out() -> pa.RecordBatch:
            words, numbers, times = np.unique(np.concatenate(hashes), return_inverse=True, return_counts=True)
            turn = np.argsort(-times, kind="stable")  # frequent words get small numbers; equally frequent ones in order of hashes
            rank = np.empty(len(turn), np.uint32)
            rank[turn] = np.arange(len(turn))
            have = np.array([i is not None for i in ids], np.uint8)
            sizes = np.array([len(h) for h in hashes], np.uint32)
            columns = (chunk, held, _pack(np.array([i or 0 for i in ids], np.int64)), _pack(have), _pack(sizes), _pack_steps(words[turn]), _pack(rank[numbers]))
            return pa.RecordBatch.from_arrays([pa.array([c], pa.int64() if k < 2 else pa.binary()) for k, c in enumerate(columns)], names=[c.split()[0] for c in CHUNKS.split(", ")])

        for b in batches:
            for doc_id, t in zip(b.column(0).to_pylist(), b.column(1)):
                w = words_of(t.as_py())
                ids.append(doc_id)
                hashes.append(np.fromiter(map(known.__getitem__, w), np.uint64, len(w)))
                held += len(w)
                if held >= chunk_words:
                    yield out()
                    ids, hashes, held, chunk = [], [], 0, chunk + 1
        if ids:
            yield out()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("text")).mapInArrow(run, CHUNKS)


def _grams(sizes: np.ndarray, words: np.ndarray, numbers: np.ndarray, order: int, shift: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """All n-grams of a chunk, order after order, and the words at which those of each order end."""
    place = _places(sizes.astype(np.int64))
    ends = [np.flatnonzero(place >= n) for n in range(order)]
    return np.concatenate([g[at] for g, at in zip(gram_hashes(words[numbers], place, order), ends)]) >> np.uint64(shift), ends


LISTS = "bucket int, chunk long, keys binary, counts binary"


def lists(told: DataFrame, order: int, buckets: int, shift: int) -> DataFrame:
    """Each chunk's different n-grams with their counts, by bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for chunk, sizes, words, numbers in zip(*[b.column(k).to_pylist() for k in range(4)]):
                grams, _ = _grams(_unpack(sizes, np.uint32), _unpack_steps(words), _unpack(numbers, np.uint32), order, shift)
                keys, counts = np.unique(grams, return_counts=True)
                del grams
                bucket = (keys >> np.uint64(32 - shift)) * np.uint64(buckets) >> np.uint64(32)
                cut = [0, *(np.flatnonzero(bucket[1:] != bucket[:-1]) + 1).tolist(), len(keys)]
                rows = [(int(bucket[x]), chunk, _pack_steps(keys[x:y]), _pack(counts[x:y].astype(np.uint32))) for x, y in zip(cut, cut[1:]) if y > x]
                for at in range(0, len(rows), 512):
                    kinds = (pa.int32(), pa.int64(), pa.binary(), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[at : at + 512]), kinds)], names=[c.split()[0] for c in LISTS.split(", ")])

    return told.select("chunk", "sizes", "words", "numbers").mapInArrow(run, LISTS)


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[list[tuple]]:
    """Runs of rows with the same first column."""
    held: list[tuple] = []
    for b in batches:
        for r in zip(*[c.to_pylist() for c in b.columns]):
            if held and r[0] != held[0][0]:
                yield held
                held = []
            held.append(r)
    if held:
        yield held


def totals(dealt: DataFrame) -> DataFrame:
    """(bucket, chunk, keys, counts) dealt and sorted by bucket -> (chunk, bucket, totals) in the order of the keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _gathered(batches):
            keys = [_unpack_steps(r[2]) for r in rows]
            table, where = np.unique(np.concatenate(keys), return_inverse=True)
            total = np.bincount(where, weights=np.concatenate([_unpack(r[3], np.uint32) for r in rows]), minlength=len(table)).astype(np.uint64)
            at = np.cumsum([0, *map(len, keys)]).tolist()
            told = [_pack(total[where[x:y]]) for x, y in zip(at, at[1:])]
            yield pa.RecordBatch.from_arrays([pa.array([r[1] for r in rows], pa.int64()), pa.array([r[0] for r in rows], pa.int32()), pa.array(told, pa.binary())], names=["chunk", "bucket", "totals"])

    return dealt.mapInArrow(run, "chunk long, bucket int, totals binary")


def log_scores(sizes: np.ndarray, words: np.ndarray, numbers: np.ndarray, total: np.ndarray, n_all: int, order: int, shift: int) -> np.ndarray:
    """Per document of a chunk the sum of log S; ``total``: counts of the chunk's different n-grams in hash order."""
    if not len(numbers):
        return np.zeros(len(sizes))
    grams, ends = _grams(sizes, words, numbers, order, shift)
    doc = np.repeat(np.arange(len(sizes), dtype=np.uint32), sizes)
    turn = np.argsort(grams, kind="stable").astype(np.uint32)  # equal n-grams of a document stay side by side
    grams, where = grams[turn], np.concatenate([doc[at] for at in ends])[turn]
    fresh = grams[1:] != grams[:-1]
    number = np.cumsum(np.concatenate([[False], fresh]), dtype=np.uint32)
    if int(number[-1]) + 1 != len(total):
        raise ValueError("totals of another chunk")
    first = np.flatnonzero(np.concatenate([[True], fresh | (where[1:] != where[:-1])]))
    del grams, where, fresh
    own = np.diff(np.concatenate([first, [len(turn)]]))
    others = np.empty(len(turn), np.int64)  # of each n-gram: its count in other documents
    others[turn] = total[number].astype(np.int64) - np.repeat(own, own)
    del turn, number, first, own
    others = np.split(others, np.cumsum([len(at) for at in ends[:-1]]))
    rest = np.maximum(n_all - np.repeat(sizes.astype(np.int64), sizes), 1)
    value = np.where(others[0] > 0, np.log(np.maximum(others[0], 1)), math.log(BACKOFF)) - np.log(rest)
    context = others[0]
    for n in range(1, order):
        at, f = ends[n], others[n]
        value[at] = np.where(f > 0, np.log(np.maximum(f, 1)) - np.log(np.maximum(context[at - 1], 1)), math.log(BACKOFF) + value[at])
        context = np.zeros(len(doc), np.int64)
        context[at] = f
    return np.bincount(doc, weights=value, minlength=len(sizes))


def scores(docs: DataFrame, *, order: int = ORDER, chunk_words: int = CHUNK_WORDS, bucket_grams: int = BUCKET_GRAMS) -> DataFrame:
    """One row per document: doc_id, n_words, log_score (natural), mean_log_score."""
    told = stored(chunks(docs, chunk_words), "lm-chunks", codec="none")
    n_all = told.agg(F.coalesce(F.sum("n_words"), F.lit(0))).first()[0]
    buckets = max(1, -(-n_all * order // bucket_grams))
    parts = min(max(buckets, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))), MOST_PARTS)
    shift = max(0, 64 - BUCKET_BITS - (buckets.bit_length() - 1))
    dealt = lists(told, order, buckets, shift).repartition(parts, "bucket").sortWithinPartitions("bucket", "chunk")
    none = F.lit(None).cast("binary")
    whole = told.select("chunk", F.lit(-1).alias("bucket"), none.alias("totals"), "doc_ids", "have", "sizes", "words", "numbers")
    counted = totals(dealt).select("chunk", "bucket", "totals", *[none.alias(c) for c in ("doc_ids", "have", "sizes", "words", "numbers")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _gathered(batches):
            doc_ids, have, sizes, numbers = (_unpack(rows[0][k], kind) for k, kind in ((3, np.int64), (4, np.uint8), (5, np.uint32), (7, np.uint32)))
            words = _unpack_steps(rows[0][6])
            total = np.concatenate([np.zeros(0, np.uint64), *[_unpack(r[2], np.uint64) for r in rows[1:]]])
            found = log_scores(sizes, words, numbers, total, n_all, order, shift)
            yield pa.RecordBatch.from_arrays([pa.array(doc_ids, mask=have == 0), pa.array(sizes.astype(np.int64)), pa.array(found)], names=["doc_id", "n_words", "log_score"])

    found = whole.unionByName(counted).repartition("chunk").sortWithinPartitions("chunk", "bucket").mapInArrow(run, "doc_id long, n_words long, log_score double")
    return found.withColumn("mean_log_score", F.when(F.col("n_words") > 0, F.col("log_score") / F.col("n_words")))
