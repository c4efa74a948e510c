"""Benchmark decontamination with a generalised suffix automaton over the words of the test items.

Normal form: ASCII letters in lower case; a word is a run of digits, letters and non-ASCII characters.  All words
of a document stream through the automaton, which gives at each word the longest item passage that ends there.
A passage of ``window`` words (or a whole item of fewer words) is a hit, and every word inside one is a hit word.

The automaton grows with the benchmark and not with the corpus.  Items are counted first; beyond ``block_words``
words they are dealt to several automata, and documents go through one after the other, still without a shuffle.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import let_go, own

WINDOW = 10
BLOCK_WORDS = 2_000_000

_WORD_BYTES = set(range(0x30, 0x3A)) | set(range(0x61, 0x7B)) | set(range(0x80, 0x100))
_NORMAL = bytes((b + 32 if 0x41 <= b <= 0x5A else b if b in _WORD_BYTES else 0x20) for b in range(256))
_PAIR_BITS = 22
_PIECE = 1 << 20


def words_of(text: bytes | str | None) -> list[bytes]:
    if text is None:
        return []
    return (text.encode() if isinstance(text, str) else text).translate(_NORMAL).split()


class ItemAutomaton:
    """Suffix automaton of several word sequences, with the items of each state and the short items that end there."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int = WINDOW):
        self.window = window
        self.vocabulary: dict[bytes, int] = {}
        self.step: list[dict[int, int]] = [{}]
        self.link = [-1]
        self.longest = [0]
        self.shortest_window = window
        owners: list[set[str]] = [set()]
        pairs: set[tuple[int, int]] = set()
        coded = [(name, [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words]) for name, words in items if words]
        for name, ids in coded:
            last = 0
            for c in ids:
                last = self._append(last, c)
                while len(owners) < len(self.step):
                    owners.append(set())
                owners[last].add(name)
            pairs.update(zip(ids, ids[1:]))
            self.shortest_window = min(self.shortest_window, len(ids))
        for v in sorted(range(1, len(self.step)), key=self.longest.__getitem__, reverse=True):
            owners[self.link[v]] |= owners[v]
        # the items of the window that ends at a state: those of its ancestor whose strings have that length
        self.window_items: list[frozenset[str]] = []
        for v in range(len(self.step)):
            u = v
            while u > 0 and self.longest[self.link[u]] >= window:
                u = self.link[u]
            self.window_items.append(frozenset(owners[u]) if self.longest[u] >= window else frozenset())
        ends: list[list[tuple[int, str]]] = [[] for _ in self.step]
        for name, ids in coded:
            if len(ids) < window:
                v = 0
                for c in ids:
                    v = self.step[v][c]
                ends[v].append((len(ids), name))
        for v in sorted(range(1, len(self.step)), key=self.longest.__getitem__):
            ends[v] = ends[v] + ends[self.link[v]]
        self.short_ends = ends
        self.pair_seen = np.zeros(1 << _PAIR_BITS, bool)
        if pairs:
            first, second = np.array(sorted(pairs), np.int64).T
            self.pair_seen[self._slot(first, second)] = True

    @staticmethod
    def _slot(first, second):
        return (first * 0x9E3779B1 + second * 0x85EBCA6B) & ((1 << _PAIR_BITS) - 1)

    def _append(self, last: int, c: int) -> int:
        step, link, longest = self.step, self.link, self.longest
        if c in step[last]:
            q = step[last][c]
            if longest[q] == longest[last] + 1:
                return q
            return self._split(last, c, q)
        new = len(step)
        step.append({})
        link.append(0)
        longest.append(longest[last] + 1)
        p = last
        while p >= 0 and c not in step[p]:
            step[p][c] = new
            p = link[p]
        if p >= 0:
            q = step[p][c]
            link[new] = q if longest[q] == longest[p] + 1 else self._split(p, c, q)
        return new

    def _split(self, p: int, c: int, q: int) -> int:
        step, link, longest = self.step, self.link, self.longest
        copy = len(step)
        step.append(dict(step[q]))
        link.append(link[q])
        longest.append(longest[p] + 1)
        link[q] = copy
        while p >= 0 and step[p].get(c) == q:
            step[p][c] = copy
            p = link[p]
        return copy

    def matches(self, ids: np.ndarray) -> tuple[list[tuple[int, int]], set[str]]:
        """Word intervals [from, to) inside some window's occurrence, merged, and the items of those windows."""
        if len(ids) < self.shortest_window:
            return [], set()
        known = ids >= 0
        linked = known[:-1] & known[1:] & self.pair_seen[self._slot(ids[:-1], ids[1:])]
        edge = np.flatnonzero(np.diff(np.concatenate(([False], linked, [False])).astype(np.int8)))
        starts, ends = edge[::2], edge[1::2] + 1  # words [start, end)
        if self.shortest_window == 1:  # a single word can be a whole item, linked to its neighbour or not
            edge = np.flatnonzero(np.diff(np.concatenate(([False], known, [False])).astype(np.int8)))
            starts, ends = edge[::2], edge[1::2]
        found: list[list[int]] = []
        items: set[str] = set()
        step, link, longest, window = self.step, self.link, self.longest, self.window
        enough = (ends - starts) >= self.shortest_window
        for a, b in zip(starts[enough].tolist(), ends[enough].tolist()):
            v = length = 0
            for at, c in enumerate(ids[a:b].tolist(), a):
                while v and c not in step[v]:
                    v = link[v]
                    length = longest[v]
                v = step[v].get(c, 0)
                length = length + 1 if v else 0
                hit = window if length >= window else 0
                if hit:
                    items |= self.window_items[v]
                for size, name in self.short_ends[v]:
                    if size <= length:
                        items.add(name)
                        hit = max(hit, size)
                if hit:
                    start = at + 1 - hit
                    while found and found[-1][0] >= start:
                        found.pop()
                    if found and found[-1][1] >= start:
                        found[-1][1] = at + 1
                    else:
                        found.append([start, at + 1])
        return [(a, b) for a, b in found], items

    def ids_of(self, text: bytes) -> np.ndarray:
        """Item-word ids of a text's words, -1 for others; works through the text in pieces cut between words."""
        out, at = [], 0
        get = self.vocabulary.get
        while at < len(text):
            end = at + _PIECE
            if end < len(text):
                while end < len(text) and _NORMAL[text[end]] != 0x20:
                    end += 1
            words = text[at:end].translate(_NORMAL).split()
            out.append(np.fromiter(map(get, words, repeat(-1)), np.int64, len(words)))
            at = end
        return np.concatenate(out) if len(out) > 1 else out[0] if out else np.zeros(0, np.int64)


def item_blocks(items: DataFrame, window: int = WINDOW, block_words: int = BLOCK_WORDS, id_col: str = "item_id", text_col: str = "text") -> Iterator[ItemAutomaton]:
    """One automaton for each block of items; the number of blocks follows the counted size of the benchmark."""
    chosen = items.select(F.coalesce(F.col(id_col).cast("string"), F.lit("null")).alias("name"), F.col(text_col).cast("binary").alias("text")).where("text is not null")
    # every word but the last needs a separator, so half the bytes bound the words
    size = chosen.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = -(-size // (2 * block_words)) or 1
    for k in range(blocks):
        rows = chosen.where(F.pmod(F.xxhash64("name"), F.lit(blocks)) == k).collect()
        yield ItemAutomaton([(r["name"], words_of(bytes(r["text"]))) for r in rows], window)


def annotate(docs: DataFrame, items: DataFrame, *, window: int = WINDOW, block_words: int = BLOCK_WORDS, text_col: str = "text") -> DataFrame:
    """docs with its text column as binary ``own('text')`` and the columns own('n_words') long, own('spans')
    array<int> (flat word intervals, merged) and own('items') array<string> (sorted).

    Null and empty texts have no words, spans or items; repeated rows are each judged; an empty benchmark hits nothing.
    """
    spark = docs.sparkSession
    rest = [c for c in docs.columns]
    out = docs.withColumns({own("text"): F.col(text_col).cast("binary"), own("n_words"): F.lit(0).cast("long"), own("spans"): F.array().cast("array<int>"), own("items"): F.array().cast("array<string>")})
    for automaton in item_blocks(items, window, block_words):
        shared = spark.sparkContext.broadcast(automaton)

        def through(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            a = shared.value
            for b in batches:
                names = b.schema.names
                at = {n: names.index(own(n)) for n in ("text", "n_words", "spans", "items")}
                counts, spans, found = [], [], []
                for text, old, seen in zip(b.column(at["text"]), b.column(at["spans"]), b.column(at["items"])):
                    ids = a.ids_of(text.as_py() or b"")
                    hit, names_hit = a.matches(ids)
                    counts.append(len(ids))
                    spans.append([x for s in merged([*pairs_of(old.as_py()), *hit]) for x in s])
                    found.append(sorted({*seen.as_py(), *names_hit}))
                columns = list(b.columns)
                columns[at["n_words"]] = pa.array(counts, pa.int64())
                columns[at["spans"]] = pa.array(spans, pa.list_(pa.int32()))
                columns[at["items"]] = pa.array(found, pa.list_(pa.string()))
                yield pa.RecordBatch.from_arrays(columns, names=names)
            let_go()

        out = out.mapInArrow(through, out.schema)
    return out.select(*rest, *[own(n) for n in ("text", "n_words", "spans", "items")])


def pairs_of(flat: list[int]) -> list[tuple[int, int]]:
    return list(zip(flat[::2], flat[1::2]))


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def contamination(docs: DataFrame, items: DataFrame, *, window: int = WINDOW, block_words: int = BLOCK_WORDS) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    a = annotate(docs.select("doc_id", "text"), items, window=window, block_words=block_words)
    spans = own("spans")
    hit = F.aggregate(F.sequence(F.lit(0), F.size(spans) - 1), F.lit(0).cast("long"), lambda s, i: s + F.when(i % 2 == 1, F.get(F.col(spans), i)).otherwise(-F.get(F.col(spans), i)))
    hit = F.when(F.size(spans) > 0, hit).otherwise(F.lit(0).cast("long"))
    return a.select("doc_id", F.col(own("n_words")).alias("n_words"), hit.alias("n_hit"), F.size(own("items")).cast("long").alias("n_items"), F.sha2(F.array_join(own("items"), ",").cast("binary"), 256).alias("items_sha256"), (F.size(spans) > 0).alias("contaminated"))


def word_bytes(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """First byte and end byte of each word."""
    kinds = np.frombuffer(text.translate(_NORMAL), np.uint8) != 0x20
    edge = np.flatnonzero(np.diff(np.concatenate(([False], kinds, [False])).astype(np.int8)))
    return edge[::2], edge[1::2]


def cleaned(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    """The text without the bytes from the first to the last word of each span."""
    if not spans:
        return text
    first, end = word_bytes(text)
    out, at = [], 0
    for a, b in spans:
        out.append(text[at : first[a]])
        at = int(end[b - 1])
    return b"".join([*out, text[at:]])


def decontaminate(docs: DataFrame, items: DataFrame, *, window: int = WINDOW, max_coverage: float = 0.5, block_words: int = BLOCK_WORDS) -> DataFrame:
    """The documents' own columns: spans found in items are cut out of ``text``, and a document of which they cover
    more than ``max_coverage`` of the words is dropped.  A null text stays null.
    """
    columns = docs.columns
    a = annotate(docs, items, window=window, block_words=block_words)
    a = a.withColumn("text", F.coalesce(F.col("text").cast("string"), F.lit(None).cast("string")))
    at_text = columns.index("text")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.schema.names
            text, spans, n = (b.column(names.index(own(x))) for x in ("text", "spans", "n_words"))
            keep, new = [], []
            for t, s, words in zip(text, spans, n.to_pylist()):
                s = pairs_of(s.as_py())
                hit = sum(y - x for x, y in s)
                keep.append(not s or hit <= max_coverage * words)
                new.append(cleaned(t.as_py(), s).decode() if s and keep[-1] else None)
            hits = pa.array([x is not None for x in new])
            replaced = pa.compute.if_else(hits, pa.array(new, b.column(at_text).type), b.column(at_text))
            out = list(b.columns)[: len(columns)]
            out[at_text] = replaced
            yield pa.RecordBatch.from_arrays(out, names=names[: len(columns)]).filter(pa.array(keep, pa.bool_()))
        let_go()

    schema = a.select(*columns).schema
    return a.mapInArrow(cut, schema)
