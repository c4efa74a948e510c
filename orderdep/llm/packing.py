"""Bounded-space online packing of token documents into sequences.

A task keeps at most ``open_windows`` partly filled windows.  A document's whole windows go out at once; its rest goes
to the open window it fits best.  When none fits, the fullest goes out, filled up with the front of the rest unless
less than ``least_cut`` is free.  When a task ends, its open windows are merged into full ones; the one that may
remain of each task is merged with those of other tasks in a last step over one row a task.

Null and empty texts are documents of the end id alone.  Rows with the same id are separate documents.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored
from .tokens import CACHE_PIECES, FEW_PIECES, encoder, forget

SEQUENCE = 1024
OPEN_WINDOWS = 64
LEAST_CUT = 8
#: Remaining windows that one task of the last step merges.
MERGE_FAN_IN = 20_000


class OpenWindows:
    """Piece: (document, start, ids).  Full sequences come out of ``put`` and ``close`` as lists of pieces."""

    def __init__(self, size: int = SEQUENCE, most: int = OPEN_WINDOWS, least_cut: int = LEAST_CUT):
        self.size, self.most, self.least_cut = size, most, least_cut
        self.free: list[tuple[int, int]] = []  # (tokens free, window), ascending
        self.pieces: dict[int, list] = {}
        self.made = 0

    def put(self, doc, ids: np.ndarray) -> Iterator[list]:
        at, n = 0, len(ids)
        while n - at >= self.size:
            yield [(doc, at, ids[at : at + self.size])]
            at += self.size
        while at < n:
            rest = n - at
            k = bisect_left(self.free, (rest, -1))
            if k < len(self.free):
                free, w = self.free.pop(k)
                self.pieces[w].append((doc, at, ids[at:]))
                at = n
                if free > rest:
                    insort(self.free, (free - rest, w))
                else:
                    yield self.pieces.pop(w)
            elif len(self.free) < self.most:
                self.pieces[self.made] = [(doc, at, ids[at:])]
                insort(self.free, (self.size - rest, self.made))
                self.made, at = self.made + 1, n
            else:
                free, w = self.free.pop(0)
                if free >= self.least_cut:
                    self.pieces[w].append((doc, at, ids[at : at + free]))
                    at += free
                yield self.pieces.pop(w)

    def close(self) -> Iterator[list]:
        """Merges what is open; all but the last that comes out are full."""
        now, free = [], self.size
        for _, w in self.free:
            for doc, at, ids in self.pieces[w]:
                while len(ids):
                    now.append((doc, at, ids[:free]))
                    took = len(now[-1][2])
                    at, ids, free = at + took, ids[took:], free - took
                    if not free:
                        yield now
                        now, free = [], self.size
        if now:
            yield now
        self.free, self.pieces = [], {}


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, open boolean"


def pack_parts(docs: DataFrame, tokenizer_file: str, end_id: int, *, size: int = SEQUENCE, open_windows: int = OPEN_WINDOWS, least_cut: int = LEAST_CUT, with_ids: bool = False, keep_encoder: bool = True) -> DataFrame:
    """Pieces by task; ``open`` marks those of the one window a task could not fill."""
    end = np.array([end_id], "<u4").tobytes()

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, task = encoder(tokenizer_file, CACHE_PIECES if keep_encoder else FEW_PIECES), TaskContext.get().partitionId() << 40
        windows, made = OpenWindows(size, open_windows, least_cut), 0
        rows: list[tuple] = []

        def note(pieces: list, open_: bool = False) -> None:
            nonlocal made
            offset = 0
            for (doc_id, total), start, ids in pieces:
                raw = ids.tobytes()
                rows.append((doc_id, start, len(ids), zlib.crc32(raw), total, task + made, offset, open_, *([raw] if with_ids else [])))
                offset += len(ids)
            made += 1

        def out() -> pa.RecordBatch:
            got = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * len(kinds), kinds)], names=names)
            rows.clear()
            return got

        kinds = [pa.int64()] * 7 + [pa.bool_()] + [pa.binary()] * with_ids
        names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "open"] + ["ids"] * with_ids
        for b in batches:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1)):
                ids = np.frombuffer(enc.encode(text.as_py()) + end, "<u4")
                for pieces in windows.put((doc_id, len(ids)), ids):
                    note(pieces)
                if len(rows) >= 5000:
                    yield out()
        for pieces in windows.close():
            note(pieces, sum(len(p[2]) for p in pieces) < size)
        yield out()
        if not keep_encoder:
            del enc
            forget()

    return docs.select("doc_id", "text").mapInArrow(packed, PIECES + ", ids binary" * with_ids)


def merge_plan(open_windows: DataFrame, size: int = SEQUENCE, fan_in: int = MERGE_FAN_IN) -> DataFrame:
    """(sequence_id, length) of remaining windows -> (sequence_id, into, base): best fit, longest first, in groups."""
    groups = -(-open_windows.count() // fan_in) or 1

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        todo = sorted(((n, s) for b in batches for s, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist())), reverse=True)
        free: list[tuple[int, int]] = []
        rows = []
        for n, s in todo:
            k = bisect_left(free, (n, -1))
            room, into = free.pop(k) if k < len(free) else (size, s)
            rows.append((s, into, size - room))
            if room > n:
                insort(free, (room - n, into))
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*rows) if rows else [[]] * 3)], names=["sequence_id", "into", "base"])

    return open_windows.repartition(groups).mapInArrow(place, "sequence_id long, into long, base long")


def pack(docs: DataFrame, tokenizer_file: str, end_id: int, *, size: int = SEQUENCE, open_windows: int = OPEN_WINDOWS, least_cut: int = LEAST_CUT, with_ids: bool = False, keep_encoder: bool = True) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids)."""
    pieces = stored(pack_parts(docs, tokenizer_file, end_id, size=size, open_windows=open_windows, least_cut=least_cut, with_ids=with_ids, keep_encoder=keep_encoder), "packed-pieces")
    remaining = pieces.where("open").groupBy("sequence_id").agg(F.sum("length").alias("length"))
    plan = merge_plan(remaining, size)
    merged = pieces.where("open").join(plan, "sequence_id").withColumns({"offset": F.col("offset") + F.col("base"), "sequence_id": F.col("into")})
    columns = [c for c in pieces.columns if c != "open"]
    return pieces.where("not open").select(columns).unionByName(merged.select(columns))
