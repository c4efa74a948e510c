"""SimHash near duplicates by multi-index hashing.

Fingerprints of 64 bits over word shingles.  Equal fingerprints are one node.  The fingerprint is cut into segments;
two fingerprints at most ``radius`` bits apart are at most ``radius // segments`` bits apart in some segment, so each
node looks up the small Hamming ball around each of its segments in that segment's table (only the half of the ball
in which the lowest differing bit is set here, since the other node looks from the other side).  All who meet at a
table entry are compared over all 64 bits, and a spanning forest of the true links goes on, never all pairs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations, islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import shuffles_dropped
from .common import let_go, own, result_of, small_batches, stored
from .components import components

RADIUS = 3
SEGMENTS = 2
_LOWER = bytes(b + 32 if 0x41 <= b <= 0x5A else b for b in range(256))
_ROWS = 1 << 15


def shingle_hashes(text: bytes, size: int) -> np.ndarray:
    """The different 64-bit hashes of a text's shingles (all its words where it has fewer)."""
    joined, firsts, ends = shingle_spans(text, size)
    return np.unique(np.fromiter((xxhash.xxh3_64_intdigest(joined[a:b]) for a, b in zip(firsts.tolist(), ends.tolist())), np.uint64, len(firsts)))


def shingle_spans(text: bytes, size: int) -> tuple[bytes, np.ndarray, np.ndarray]:
    """Words in lower case (A-Z) joined by spaces, with the first and end byte of every shingle."""
    words = text.translate(_LOWER).split()
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    firsts = np.concatenate([[0], ends[:-1] + 1]) if len(words) else ends
    n = max(1, len(words) - size + 1) if len(words) else 0
    return b" ".join(words), firsts[:n], ends[-n:] if n else ends


def fingerprint(text: bytes, size: int, seed: int = 42) -> int:
    """Signed 64-bit fingerprint: a bit is set where over half of the shingles' hashes have it; no words: zero."""
    joined, firsts, ends = shingle_spans(text, size)
    n, digest = len(firsts), xxhash.xxh64_digest
    if not n:
        return 0
    counts = np.zeros(64, np.int64)
    for at in range(0, n, _ROWS):
        raw = b"".join([digest(joined[a:b], seed) for a, b in zip(firsts[at : at + _ROWS].tolist(), ends[at : at + _ROWS].tolist())])
        counts += np.unpackbits(np.frombuffer(raw, np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big", signed=True)


def fingerprints(docs: DataFrame, *, shingle_words: int = 3, seed: int = 42) -> DataFrame:
    """(doc_id, fp long).  Null text: no words, fingerprint zero."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([fingerprint(t.as_py() or b"", shingle_words, seed) for t in b.column(1)], pa.int64())], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text")).mapInArrow(run, "doc_id long, fp long")


def lookups(nodes: DataFrame, radius: int = RADIUS, segments: int = SEGMENTS) -> DataFrame:
    """(entry, home, fp): each node at its own entry of each segment's table, and at the entries its balls reach."""
    if 64 % segments:
        raise ValueError("segments must divide 64")
    bits = 64 // segments
    masks = [sum(1 << k for k in ks) for r in range(radius // segments + 1) for ks in combinations(range(bits), r)]
    masks = [m - (1 << 64) if m >= 1 << 63 else m for m in masks]

    def reaches(mask):
        return (mask == 0) | (mask.bitwiseAND(-mask).bitwiseAND(F.col("value")) != 0)

    tables = []
    for s in range(segments):
        value = F.shiftrightunsigned("fp", s * bits).bitwiseAND(F.lit((1 << bits) - 1 if bits < 64 else -1))
        ball = nodes.select("fp", value.alias("value")).withColumn("mask", F.explode(F.filter(F.array(*[F.lit(m).cast("long") for m in masks]), reaches)))
        tables.append(ball.select(F.lit(s).alias("segment"), F.col("value").bitwiseXOR(F.col("mask")).alias("entry"), (F.col("mask") == 0).alias("home"), "fp"))
    out = tables[0]
    for t in tables[1:]:
        out = out.union(t)
    return out


def forest(fps: np.ndarray, home: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """A spanning forest of the true links among those who meet at an entry, grown from each node at home there.

    Every tree takes the closest open node next, so its edges are the shortest that hold it together.
    """
    bits = fps.view(np.uint64)
    open_ = np.ones(len(fps), bool)
    out: list[tuple[int, int]] = []
    for start in np.flatnonzero(home).tolist():
        if not open_[start]:
            continue
        open_[start] = False
        left = np.flatnonzero(open_)
        gap = np.bitwise_count(bits[left] ^ bits[start])
        by = np.full(len(left), start)
        while len(left):
            k = int(gap.argmin())
            if gap[k] > radius:
                break
            v = int(left[k])
            out.append((int(fps[by[k]]), int(fps[v])))
            open_[v] = False
            left, gap, by = np.delete(left, k), np.delete(gap, k), np.delete(by, k)
            new = np.bitwise_count(bits[left] ^ bits[v])
            closer = new < gap
            gap[closer], by[closer] = new[closer], v
    return out


def links(nodes: DataFrame, radius: int = RADIUS, segments: int = SEGMENTS) -> DataFrame:
    """nodes (fp) distinct -> edges (a, b) that span every group of nodes linked by at most ``radius`` bits."""
    rows = lookups(nodes, radius, segments).repartition("segment", "entry").sortWithinPartitions("segment", "entry")

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def edges(seg, entry, home, fps) -> list[tuple[int, int]]:
            new = np.flatnonzero((seg[1:] != seg[:-1]) | (entry[1:] != entry[:-1])) + 1
            first = np.concatenate([[0], new])
            size = np.diff(np.concatenate([first, [len(entry)]]))
            busy = (size > 1) & (np.add.reduceat(home.astype(np.int64), first) > 0)
            out: list[tuple[int, int]] = []
            for a, n in zip(first[busy].tolist(), size[busy].tolist()):
                out += forest(fps[a : a + n], home[a : a + n], radius)
            return out

        def batch_of(found) -> pa.RecordBatch:
            a = np.array(found, np.int64).reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(a[:, 0]), pa.array(a[:, 1])], names=["a", "b"])

        for b in batches:
            now = [b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy(zero_copy_only=False), b.column(3).to_numpy()]
            if held:
                now = [np.concatenate([x, y]) for x, y in zip(held, now)]
            last = np.flatnonzero((now[0] != now[0][-1]) | (now[1] != now[1][-1]))
            cut = int(last[-1]) + 1 if len(last) else 0
            if cut:
                yield batch_of(edges(*[x[:cut] for x in now]))
            held = [x[cut:] for x in now]
        if held and len(held[0]):
            yield batch_of(edges(*held))
        let_go()

    return rows.mapInArrow(meet, "a long, b long")


def grouped(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """nodes (fp, first_doc), edges (a, b) -> (fp, component_id): the smallest doc_id reached from each fingerprint."""
    member = nodes.join(components(edges).withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    lowest = member.groupBy("root").agg(F.min("first_doc").alias("component_id"))
    return member.join(lowest, "root").select("fp", "component_id")


def classes(prints: DataFrame, radius: int = RADIUS, segments: int = SEGMENTS) -> DataFrame:
    """prints (doc_id, fp) -> (fp, component_id)."""
    nodes = stored(prints.groupBy("fp").agg(F.min("doc_id").alias("first_doc")), "simhash-nodes")
    return grouped(nodes, links(nodes.select("fp"), radius, segments))


def near_duplicates(docs: DataFrame, *, shingle_words: int = 3, radius: int = RADIUS, segments: int = SEGMENTS) -> DataFrame:
    """One row per document: doc_id, fp long, component_id."""
    prints = stored(fingerprints(docs, shingle_words=shingle_words), "simhash-prints")
    return prints.join(classes(prints, radius, segments), "fp").select("doc_id", "fp", "component_id")


#: For near duplicates by resemblance: words of a shingle and the share of shingles that two texts must have in common;
#: tables, and minima that two texts must share to meet in one.  A pair at similarity s meets nowhere with probability
#: (1 - s ** MINIMA) ** TABLES: 5e-8 at 0.8.
SHINGLE_WORDS, LEAST_SIMILARITY = 5, 0.8
TABLES, MINIMA = 32, 4
#: Least hashes of a shingle set that go with a text into its entries; a set of no more of them is there as a whole.
LEAST_HASHES = 256
#: Further orders in which neighbours at an entry are tested before all pairs that are left.
CHAINS = 1
#: Words of 64 bits up to which ``picked`` sends its bitmap to all executors: a bit a row, 67 million rows.
MOST_WORDS = 1 << 20
_DRAWN = np.random.Generator(np.random.PCG64(42)).integers(0, 1 << 64, (2, TABLES * MINIMA, 1), np.uint64)
_TIMES, _PLUS = _DRAWN[0] | np.uint64(1), _DRAWN[1]
_TIED = np.random.Generator(np.random.PCG64(43)).integers(0, 1 << 64, (TABLES, MINIMA), np.uint64) | np.uint64(1)


def minima(shingles: np.ndarray) -> np.ndarray:
    """The least shingle in each of ``TABLES * MINIMA`` orders."""
    low = np.full(TABLES * MINIMA, (1 << 64) - 1, np.uint64)
    for at in range(0, len(shingles), 4096):
        low = np.minimum(low, (shingles[at : at + 4096] * _TIMES + _PLUS).min(1))
    return low


def table_entries(shingles: np.ndarray) -> np.ndarray:
    """A text's entry in each table: a hash of the table and of the least shingles in ``MINIMA`` orders of its own."""
    # every table has factors of its own, so that equal minima of two tables do not meet
    return (minima(shingles).reshape(TABLES, MINIMA) * _TIED).sum(1, dtype=np.uint64)


def sketch(shingles: np.ndarray) -> bytes:
    """A byte of each of the least shingles: two texts at similarity s agree in s of them or a little more."""
    return ((minima(shingles) * _TIMES[0]) >> np.uint64(56)).astype(np.uint8).tobytes()


def fingerprint_entries(nodes: DataFrame) -> DataFrame:
    """nodes (fp, print, row) -> (entry, place, fp): texts whose fingerprints multi-index hashing links, together or by way of
    others, have their class for an entry; those alone in their class are left out."""
    prints = stored(nodes.groupBy(F.col("print").alias("fp")).agg(F.min("row").alias("first_doc"), F.count("*").alias("texts")), "simhash-prints")
    edges = stored(links(prints.select("fp")), "simhash-edges")
    known = grouped(prints, edges).join(prints.select("fp", "texts"), "fp")
    more = known.groupBy("component_id").agg(F.sum("texts").alias("n")).where("n > 1").select("component_id")
    classes_ = known.join(more, "component_id", "left_semi").select(F.col("fp").alias("print"), "component_id")
    return nodes.join(classes_, "print").select(F.xxhash64(F.lit("fingerprint"), "component_id").alias("entry"), F.lit(TABLES).alias("place"), "fp")


def meeting(entries: DataFrame) -> DataFrame:
    """entries (entry, place, fp) -> those rows that are not alone at their entry, with the one before them there (null for the first)."""
    there = Window.partitionBy("entry").orderBy("fp")
    both = entries.withColumns({"before": F.lag("fp").over(there), "after": F.lead("fp").over(there)})
    return both.where(F.col("before").isNotNull() | F.col("after").isNotNull()).drop("after")


def shingle_sets(texts: DataFrame, shingle_words: int) -> DataFrame:
    """texts (fp, text binary) -> (fp, n long: size of the shingle set, sketch binary, low binary: the least hashes, text)."""

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                sets = [shingle_hashes(t.as_py() or b"", shingle_words) for t in b.column(1).slice(at, 256)]
                columns = [b.column(0).slice(at, 256), pa.array([len(x) for x in sets], pa.int64()), pa.array([sketch(x) for x in sets], pa.binary()), pa.array([x[:LEAST_HASHES].tobytes() for x in sets], pa.binary()), b.column(1).slice(at, 256)]
                yield pa.RecordBatch.from_arrays(columns, names=["fp", "n", "sketch", "low", "text"])
        let_go()

    return texts.select("fp", "text").mapInArrow(hashed, "fp long, n long, sketch binary, low binary, text binary")


def resemblance(a: np.ndarray, b: np.ndarray) -> tuple[float, int]:
    """Share of the least hashes of both sets together that are in both, and how many there are of them."""
    c = np.sort(np.concatenate([a, b]))
    twice = np.concatenate([c[1:] == c[:-1], [False]])
    first = np.flatnonzero(np.concatenate([[True], ~twice[:-1]]))
    if max(len(a), len(b)) == LEAST_HASHES:
        first = first[:LEAST_HASHES]
    return float(twice[first].mean()), len(first)


def first_table(same: np.ndarray) -> np.ndarray:
    """The first table in which the texts of each pair meet by the bytes they share; ``TABLES`` if only their fingerprints do."""
    met = same.reshape(-1, TABLES, MINIMA).all(2)
    return np.where(met.any(1), met.argmax(1), TABLES)


def likely_pairs(rows: DataFrame, size: DataFrame, least: float) -> DataFrame:
    """rows (entry, place, fp, root), size (fp, n, sketch, low) -> pairs (a, b) of an entry with different roots that may resemble.

    Sizes, then sketches, then the least hashes must allow ``least``; a pair at ``least`` fails the two estimates with
    probability 2e-7 each at 0.8 (five standard deviations).  Sketches go to all rows of an entry, the least hashes only to those
    whose sketch fits another's there.  Sets that are there as a whole are compared exactly, and
    of their links only those leave an entry that join texts not yet held together.  Nothing else leaves it, and each
    pair only the entry of the first table in which its texts meet (a class of fingerprints comes after all tables).
    """
    lanes = TABLES * MINIMA
    off = 5 * math.sqrt(least * (1 - least))
    agree = math.floor(lanes * (least - off / math.sqrt(lanes)))

    def fitting(place: int, marks: np.ndarray, i: int, other: np.ndarray) -> Iterator[np.ndarray]:
        """Those of ``other`` whose sketches fit that of i, in parts."""
        for at in range(0, len(other), 1 << 14):
            some = other[at : at + (1 << 14)]
            same = marks[some] == marks[i]
            some, same = (x[same.sum(1) >= agree] for x in (some, same))
            if len(some):
                yield some[first_table(same) == place]

    def fit(place: int, fp: np.ndarray, root: np.ndarray, n: np.ndarray, marks: np.ndarray) -> np.ndarray:
        turn = np.argsort(n, kind="stable")
        fp, root, n, marks = fp[turn], root[turn], n[turn], marks[turn]
        end = np.searchsorted(n, n / least, side="right")
        fits = np.zeros(len(fp), bool)
        for i in range(len(fp) - 1):
            other = np.flatnonzero((root[i + 1 : end[i]] != root[i]) & ~(fits[i] & fits[i + 1 : end[i]])) + i + 1
            for some in fitting(place, marks, i, other):
                fits[some] = True
                fits[i] |= len(some) > 0
        return fp[fits]

    def pairs(place: int, fp: np.ndarray, root: np.ndarray, n: np.ndarray, marks: np.ndarray, low: np.ndarray) -> Iterator[tuple[int, int]]:
        turn = np.argsort(n, kind="stable")
        fp, root, n, marks, low = fp[turn], root[turn], n[turn], marks[turn], low[turn]
        end = np.searchsorted(n, n / least, side="right")
        for i in range(len(fp) - 1):
            other = np.flatnonzero(root[i + 1 : end[i]] != root[i]) + i + 1
            for some in fitting(place, marks, i, other):
                for j in some.tolist():
                    if root[i] == root[j]:
                        continue
                    share, of = resemblance(low[i], low[j])
                    whole = max(len(low[i]), len(low[j])) < LEAST_HASHES
                    if share < (least if whole else least - off / math.sqrt(of)):
                        continue
                    if whole:
                        root[root == root[j]] = root[i]
                    yield min(int(fp[i]), int(fp[j])), max(int(fp[i]), int(fp[j]))

    def entries_of(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
        """The columns of each entry: entry, place, fp, root, n, sketches as rows of bytes, least hashes if they are there."""
        held: list[list[np.ndarray]] = []
        for b in batches:
            if not b.num_rows:
                continue
            now = [b.column(k).to_numpy() for k in range(5)]
            now.append(np.frombuffer(b"".join(b.column(5).to_pylist()), np.uint8).reshape(-1, lanes))
            if b.num_columns > 6:
                low = np.empty(len(now[0]), object)
                low[:] = [np.frombuffer(x, np.uint64) for x in b.column(6).to_pylist()]
                now.append(low)
            cuts = [0, *(np.flatnonzero(now[0][1:] != now[0][:-1]) + 1).tolist(), len(now[0])]
            for x, y in zip(cuts, cuts[1:]):
                if held and held[0][0][0] != now[0][x]:
                    yield [np.concatenate(c) for c in zip(*held)]
                    held.clear()
                held.append([c[x:y].copy() for c in now])
        if held:
            yield [np.concatenate(c) for c in zip(*held)]

    def batch_of(found: list[tuple[int, int]], names: list[str]) -> pa.RecordBatch:
        both = np.array(found, np.int64).reshape(-1, 2)
        return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], names=names)

    def in_batches(found: Iterator[tuple[int, int]], names: list[str]) -> Iterator[pa.RecordBatch]:
        while some := list(islice(found, 1 << 16)):
            yield batch_of(some, names)
        let_go()

    def fits_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return in_batches(((int(entry[0]), x) for entry, place, *rest in entries_of(batches) for x in fit(int(place[0]), *rest).tolist()), ["entry", "fp"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return in_batches((pair for _, place, *rest in entries_of(batches) for pair in pairs(int(place[0]), *rest)), ["a", "b"])

    def dealt(df: DataFrame, *more: str) -> DataFrame:
        return df.select("entry", "place", "fp", "root", "n", "sketch", *more).repartition("entry").sortWithinPartitions("entry")

    fits = stored(dealt(rows.join(size.select("fp", "n", "sketch"), "fp")).mapInArrow(fits_of, "entry long, fp long"), "simhash-fits")
    return dealt(rows.join(fits, ["entry", "fp"], "left_semi").join(size, "fp"), "low").mapInArrow(run, "a long, b long")


def resembling(edges: DataFrame, sets: DataFrame, least: float, shingle_words: int = SHINGLE_WORDS) -> DataFrame:
    """edges (a, b) whose texts (fp, text) have at least ``least`` of their shingles in common (Jaccard).

    Texts travel, not their sets: a set has 8 bytes for each word of the text, and they do not compress.
    """

    def alike(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, y = None, np.empty(0, np.uint64)
        for b in batches:
            keep = []
            for fp, one, two in zip(b.column(1).to_pylist(), b.column(2), b.column(3)):
                if fp != last:  # rows come by b
                    last, y = fp, shingle_hashes(two.as_py() or b"", shingle_words)
                x = shingle_hashes(one.as_py() or b"", shingle_words)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(both >= least * (len(x) + len(y) - both))
            yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))
        let_go()

    one = edges.join(sets.select(F.col("fp").alias("a"), F.col("text").alias("ta")), "a")
    two = one.join(sets.select(F.col("fp").alias("b"), F.col("text").alias("tb")), "b")
    return two.select("a", "b", "ta", "tb").mapInArrow(alike, "a long, b long")


def true_links(met: DataFrame, sets: DataFrame, least: float, shingle_words: int = SHINGLE_WORDS) -> DataFrame:
    """met (entry, place, fp, before) -> edges (a, b) with the components that testing every pair of every entry would give.

    Neighbours at an entry are tested first, then neighbours in other orders that the links found so far do not hold
    together, and at last the likely pairs of an entry that they still do not.  So a group of n copies costs some n tests,
    and texts that meet without being copies are compared by sketches inside their entry.
    """
    edges = stored(met.where("before is not null").select(F.col("before").alias("a"), F.col("fp").alias("b")).distinct(), "simhash-links")
    size = sets.select("fp", "n", "sketch", "low")
    tested, true = edges, stored(resembling(edges, sets, least, shingle_words), "simhash-true")
    for turn in range(CHAINS + 1):
        roots = components(true).withColumnRenamed("node", "fp")
        rows = met.select("entry", "place", "fp").join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
        split = rows.groupBy("entry").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select("entry")
        rows = rows.join(split, "entry", "left_semi")
        if turn < CHAINS:
            there = Window.partitionBy("entry").orderBy(F.xxhash64("fp", F.lit(turn)))
            pairs = rows.withColumns({"a": F.lag("fp").over(there), "ra": F.lag("root").over(there)}).where("ra <> root").select(F.least("a", "fp").alias("a"), F.greatest("a", "fp").alias("b"))
        else:
            pairs = likely_pairs(rows, size, least)
        # a set of under ``least`` of another's size cannot share that much with it
        new = pairs.distinct().join(tested, ["a", "b"], "left_anti").join(size.selectExpr("fp AS a", "n AS na"), "a").join(size.selectExpr("fp AS b", "n AS nb"), "b")
        edges = stored(new.where(F.least("na", "nb") >= F.greatest("na", "nb") * least).select("a", "b"), "simhash-links")
        if not edges.isEmpty():
            true = stored(true.union(resembling(edges, sets, least, shingle_words)), "simhash-true")
            tested = tested.union(edges)
    return true


def one_of_each(docs: DataFrame, *, shingle_words: int = SHINGLE_WORDS, least: float = LEAST_SIMILARITY) -> DataFrame:
    """The documents that stay, with their own columns: the one with the smallest doc_id of each group of near duplicates.

    Candidates are texts whose fingerprints over shingles multi-index hashing links, as in ``near_duplicates``; a link holds
    if the texts share ``least`` of their word shingles.  At ``least`` fingerprints differ in some ten bits, far beyond any
    radius with small balls, so that texts which share an entry of a table of least shingles are candidates too.
    Texts of the same words in the same order are one node (64-bit hash of all words).  Of several rows with the smallest id one stays; rows without an
    id come last, so one of them stays only where its group has no other.
    """
    with shuffles_dropped(docs.sparkSession), small_batches(docs.sparkSession):
        return result_of(lambda: _one_of_each(docs, shingle_words, least), docs.sparkSession, "simhash-kept")


def picked(df: DataFrame, row: str, rows: DataFrame) -> DataFrame:
    """The rows of df whose number (column ``row``) is one of ``rows`` (row), by a bitmap of the numbers, so that texts do not move."""
    word, bits = own("word"), own("bits")
    bitmap = rows.select(F.expr("row >> 6").alias(word), F.expr("shiftleft(1L, CAST(row & 63 AS INT))").alias("bit"))
    bitmap = stored(bitmap.groupBy(word).agg(F.bit_or("bit").alias(bits)), "simhash-bitmap")
    bitmap = F.broadcast(bitmap) if bitmap.limit(MOST_WORDS + 1).count() <= MOST_WORDS else bitmap
    there = df.withColumn(word, F.expr(f"{row} >> 6")).join(bitmap, word)
    return there.where(f"shiftright({bits}, CAST({row} & 63 AS INT)) & 1 = 1").select(*df.columns)


def _one_of_each(docs: DataFrame, shingle_words: int, least: float) -> DataFrame:
    columns = docs.columns
    id_, fp, row, at_, print_ = own("id"), own("fp"), own("row"), own("entries"), own("print")
    zero = F.lit(0).cast("long")
    keyed = docs.withColumns({id_: F.coalesce(F.col("doc_id").cast("long"), F.lit((1 << 63) - 1)), fp: zero, row: zero, at_: F.array().cast("array<bigint>"), print_: zero})
    at_text, n = columns.index("text"), len(columns)

    def marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 33
        for b in batches:
            texts = [(t.as_py() or "").encode() for t in b.column(at_text)]
            cols = list(b.columns)
            cols[n + 1] = pa.array(np.array([xxhash.xxh3_64_intdigest(shingle_spans(t, 1)[0]) for t in texts], np.uint64).view(np.int64))
            cols[n + 2] = pa.array(range(number, number + len(texts)), pa.int64())
            cols[n + 3] = pa.array([table_entries(shingle_hashes(t, shingle_words)).view(np.int64) for t in texts], pa.list_(pa.int64()))
            cols[n + 4] = pa.array([fingerprint(t, shingle_words) for t in texts], pa.int64())
            number += len(texts)
            yield pa.RecordBatch.from_arrays(cols, names=b.schema.names)
        let_go()

    base = stored(keyed.mapInArrow(marked, keyed.schema), "simhash-documents")
    first = F.min(F.struct(id_, row, print_)).alias("first")
    nodes = stored(base.groupBy(F.col(fp).alias("fp")).agg(first).select("fp", F.col(f"first.{row}").alias("row"), F.col(f"first.{id_}").alias("id"), F.col(f"first.{print_}").alias("print")), "simhash-nodes")
    firsts = picked(base.select(row, fp, at_), row, nodes.select("row"))
    entries = firsts.select(F.posexplode(at_).alias("place", "entry"), F.col(fp).alias("fp")).select("entry", "place", "fp")
    met = stored(meeting(entries.union(fingerprint_entries(nodes))), "simhash-met")
    texts = picked(base.select(row, fp, "text"), row, nodes.join(met.select("fp").distinct(), "fp", "left_semi").select("row"))
    texts = texts.select(F.col(fp).alias("fp"), F.col("text").cast("string").cast("binary").alias("text"))
    true = true_links(met, stored(shingle_sets(texts, shingle_words), "simhash-shingles"), least, shingle_words)
    member = nodes.join(components(true).withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    stays = stored(member.groupBy("root").agg(F.min(F.struct("id", "row")).alias("m")).select("m.row"), "simhash-stays")
    return picked(base, row, stays).select(*columns)
