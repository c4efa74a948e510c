"""Removal of every byte inside a 200-byte string that also starts anywhere else, by suffix sorting.

1. Sieve.  Each text is cut into runs of window starts (window_sieve): equal windows lie in runs of one key, at the
   same distance from the anchor.  A key met once has no repeated window; one that is always met with the same
   bytes is repeated all over.  Only the others need sorting, and of those each different run once.
2. Suffix sorting.  Runs are dealt out by key; each task gathers whole keys into buffers and builds their suffix
   array by a difference cover modulo 3 (sort the sampled triples, recurse on their names, sort the rest by the
   ranks behind them, merge), then compares the prefixes of neighbouring suffixes.
3. A key with very many different runs (a passage with everyone's own words around it) would land in one task, so
   its windows are counted one by one instead, by aggregation with a partial step.

Nulls are empty texts.  Repeated rows are repeats of each other.  A text shorter than a window keeps all its bytes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored
from .window_sieve import runs

LENGTH = 200
#: Codes that are suffix-sorted together at most: three names of the first recursion must fit 63 bits.
MOST_CODES = 3_000_000
#: Bytes after which a buffer of whole keys is suffix-sorted.
BUFFER = 1 << 19
#: Different runs of a key (of at most 368 bytes) beyond which its windows are counted one by one.
CROWD = 6000
_NO_ID = -(1 << 63)


def suffix_array(codes: np.ndarray) -> np.ndarray:
    """Suffix order of an array of codes of 1 or more, by a difference cover modulo 3."""
    if len(codes) > MOST_CODES:
        raise ValueError(f"more than {MOST_CODES} codes")
    n = len(codes)
    if n < 2:
        return np.arange(n)
    s = np.concatenate([codes.astype(np.int64), np.zeros(3, np.int64)])
    base = int(s.max()) + 1
    ones, twos = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)
    sample = np.concatenate([ones, twos])
    triple = (s[sample] * base + s[sample + 1]) * base + s[sample + 2]
    order = np.argsort(triple)
    ordered = triple[order]
    names = np.empty(len(sample), np.int64)
    names[order] = np.cumsum(np.concatenate([[1], ordered[1:] != ordered[:-1]]))
    if len(sample) and names.max() < len(sample):
        order = suffix_array(names)
    rank = np.zeros(n + 3, np.int64)
    by_rank = sample[order]
    rank[by_rank] = np.arange(1, len(sample) + 1)
    rest = np.arange(0, n, 3)
    wide = len(sample) + 2
    near = s[rest] * wide + rank[rest + 1]
    turn = np.argsort(near)
    rest, near = rest[turn], near[turn]
    far = (s[rest] * base + s[rest + 1]) * wide + rank[rest + 2]
    is_one = by_rank % 3 == 1
    a, b = by_rank[is_one], by_rank[~is_one]
    near_a = s[a] * wide + rank[a + 1]
    far_b = (s[b] * base + s[b + 1]) * wide + rank[b + 2]
    before = np.empty(len(sample), np.int64)  # how many of the rest come before each of the sample
    before[is_one], before[~is_one] = np.searchsorted(near, near_a), np.searchsorted(far, far_b)
    out = np.empty(len(sample) + len(rest), np.int64)
    out[np.arange(len(sample)) + before] = by_rank
    out[np.arange(len(rest)) + np.searchsorted(near_a, near) + np.searchsorted(far_b, far)] = rest
    return out[out < n]


def repeated_starts(texts: list[bytes], length: int) -> np.ndarray:
    """For each byte of the joined texts: a window starts here, lies in its text, and starts elsewhere too."""
    data = np.frombuffer(b"".join(texts), np.uint8)
    sizes = np.array([len(t) for t in texts])
    ends = np.cumsum(sizes)
    at = np.arange(len(data))
    inside = at + length <= np.repeat(ends, sizes)
    order = suffix_array(data.astype(np.int64) + 1)
    order = order[inside[order]]
    words = np.lib.stride_tricks.sliding_window_view(np.concatenate([data, np.zeros(8, np.uint8)]), 8)
    words = np.ascontiguousarray(words).view(np.uint64).ravel()
    first, second = order[:-1], order[1:]
    for step in [*range(0, length - 7, 8), *([length - 8] if length % 8 else [])]:
        same = words[first + step] == words[second + step]
        first, second = first[same], second[same]
    out = np.zeros(len(data), bool)
    out[first] = True
    out[second] = True
    return out


def _pairs(flags: np.ndarray) -> list[int]:
    """Flat [from, to) intervals of the set flags."""
    edge = np.flatnonzero(np.diff(np.concatenate(([False], flags, [False])).astype(np.int8)))
    return edge.tolist()


RUNS = "did long, th long, anchor long, content long, n int, starts array<int>"


def run_rows(source: DataFrame, length: int) -> DataFrame:
    """source (did, th, text binary) -> one row for each document and different run: where it starts, how many starts."""

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            dids, ths = b.column(0).to_numpy(), b.column(1).to_numpy()
            for doc, start, n, anchor, content in runs([t.as_py() for t in b.column(2)], length):
                order = np.lexsort((start, content, anchor, doc))
                d, a, c = doc[order], anchor[order], content[order]
                first = np.flatnonzero(np.concatenate([[True], (d[1:] != d[:-1]) | (a[1:] != a[:-1]) | (c[1:] != c[:-1])]))
                starts = pa.ListArray.from_arrays(pa.array(np.concatenate([first, [len(d)]]).astype(np.int32)), pa.array(start[order].astype(np.int32)))
                yield pa.RecordBatch.from_arrays([pa.array(dids[d[first]]), pa.array(ths[d[first]]), pa.array(a[first]), pa.array(c[first]), pa.array(n[order][first].astype(np.int32)), starts], names=["did", "th", "anchor", "content", "n", "starts"])

    return source.mapInArrow(out, RUNS)


def sorted_repeats(bodies: DataFrame, length: int) -> DataFrame:
    """(anchor, content, body) -> (anchor, content, ranges): starts that a suffix array of whole keys finds repeated."""

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, int, bytes]] = []
        size = 0

        def found() -> pa.RecordBatch:
            flags = repeated_starts([x[2] for x in held], length)
            rows, at = [], 0
            for anchor, content, body in held:
                ranges = _pairs(flags[at : at + len(body)])
                if ranges:
                    rows.append((anchor, content, ranges))
                at += len(body)
            return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.list_(pa.int32())))], names=["anchor", "content", "ranges"])

        for b in batches:
            for anchor, content, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                if size >= BUFFER and anchor != held[-1][0]:
                    yield found()
                    held, size = [], 0
                held.append((anchor, content, body.as_py()))
                size += len(held[-1][2])
        if held:
            yield found()

    return bodies.select("anchor", "content", "body").repartition("anchor").sortWithinPartitions("anchor", "content").mapInArrow(out, "anchor long, content long, ranges array<int>")


def counted_repeats(bodies: DataFrame, length: int) -> DataFrame:
    """The same for crowded keys: windows are counted by their 128-bit hash under the key."""

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for anchor, content, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                body = body.as_py()
                n = len(body) - length + 1
                digest = np.frombuffer(b"".join([xxhash.xxh3_128_digest(body[i : i + length]) for i in range(n)]), np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, anchor)), pa.array(np.full(n, content)), pa.array(np.arange(n, dtype=np.int32)), pa.array(digest[:, 0].copy()), pa.array(digest[:, 1].copy())], names=["anchor", "content", "at", "w1", "w2"])

    windows = bodies.select("anchor", "content", "body").mapInArrow(out, "anchor long, content long, at int, w1 long, w2 long")
    twice = windows.groupBy("w1", "w2").agg(F.count("*").alias("c")).where("c > 1").select("w1", "w2")
    starts = windows.join(twice, ["w1", "w2"]).groupBy("anchor", "content").agg(F.array_sort(F.collect_list("at")).alias("at"))
    return starts.select("anchor", "content", F.flatten(F.transform("at", lambda x: F.array(x, x + 1))).alias("ranges"))


def repeated_spans(docs: DataFrame, length: int = LENGTH) -> tuple[DataFrame, DataFrame]:
    """(documents keyed by (did, th), found: (did, th, runs)): for each text the runs with their repeated starts."""
    spark = docs.sparkSession
    text = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    source = docs.select("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(_NO_ID)).alias("did"), F.xxhash64(text).alias("th"), text.alias("text"))
    rows = run_rows(source.select("did", "th", "text"), length)
    times = F.size("starts").cast("long")
    keys = rows.groupBy("anchor").agg(F.sum(times).alias("c"), F.min("content").alias("lo"), F.max("content").alias("hi")).where("c > 1")
    keys = stored(keys.select("anchor", (F.col("lo") != F.col("hi")).alias("mixed")), "suffix-keys")
    spark.sparkContext._jvm.System.gc()  # lets go of shuffle files that nothing reads any more
    hits = stored(rows.join(keys, "anchor"), "suffix-hits")
    spark.sparkContext._jvm.System.gc()
    mixed = hits.where("mixed")
    contents = mixed.groupBy("anchor", "content").agg(F.sum(times).alias("copies"), F.min(F.struct("did", "th", F.col("n"), F.get("starts", F.lit(0)).alias("start"))).alias("at"))
    contents = stored(contents, "suffix-contents")
    crowds = stored(contents.groupBy("anchor").agg(F.count("*").alias("c")).where(F.col("c") > CROWD).select("anchor", F.lit(True).alias("crowded")), "suffix-crowds")
    told = contents.join(crowds, "anchor", "left").withColumn("crowded", F.coalesce("crowded", F.lit(False)))
    picks = told.groupBy(F.col("at.did").alias("did"), F.col("at.th").alias("th")).agg(F.collect_list(F.struct("anchor", "content", "crowded", F.col("at.start").alias("start"), F.col("at.n").alias("n"))).alias("picks"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for t, p in zip(b.column(0), b.column(1)):
                t, p = t.as_py(), p.as_py()
                yield pa.RecordBatch.from_pydict({"anchor": pa.array([x["anchor"] for x in p], pa.int64()), "content": pa.array([x["content"] for x in p], pa.int64()), "crowded": pa.array([x["crowded"] for x in p], pa.bool_()), "body": pa.array([t[x["start"] : x["start"] + x["n"] + length - 1] for x in p], pa.binary())})

    bodies = source.join(picks, ["did", "th"]).select("text", "picks").mapInArrow(cut, "anchor long, content long, crowded boolean, body binary")
    # rows with equal id and text pick the same runs
    bodies = stored(bodies, "suffix-bodies")
    spark.sparkContext._jvm.System.gc()
    single = bodies.dropDuplicates(["anchor", "content"]) if _has_twins(contents, bodies) else bodies
    found = sorted_repeats(single.where("not crowded"), length).unionByName(counted_repeats(single.where("crowded"), length))
    whole = lambda n: F.array(F.lit(0), F.col(n))
    copied = contents.where("copies > 1").select("anchor", "content", whole("at.n").alias("ranges"))
    verdicts = stored(found.unionByName(copied), "suffix-verdicts")
    spans = mixed.join(verdicts, ["anchor", "content"]).select("did", "th", "starts", "ranges").unionByName(hits.where("not mixed").select("did", "th", "starts", whole("n").alias("ranges")))
    per_text = stored(spans.groupBy("did", "th").agg(F.collect_set(F.struct("starts", "ranges")).alias("runs")), "suffix-spans")
    for t in (bodies, keys):
        discard(t)
    spark.sparkContext._jvm.System.gc()
    return source, per_text


def _has_twins(contents: DataFrame, bodies: DataFrame) -> bool:
    return contents.count() != bodies.count()


def _covered(size: int, found: list[dict], length: int) -> list[tuple[int, int]]:
    """Merged byte intervals of all repeated windows of a text."""
    if not found:
        return []
    edge = np.zeros(size + 1, np.int32)
    for run in found:
        starts, ranges = np.array(run["starts"]), np.array(run["ranges"]).reshape(-1, 2)
        np.add.at(edge, (starts[:, None] + ranges[None, :, 0]).ravel(), 1)
        np.add.at(edge, (starts[:, None] + ranges[None, :, 1] + length - 1).ravel(), -1)
    flat = _pairs(np.cumsum(edge[:-1]) > 0)
    return list(zip(flat[::2], flat[1::2]))


def removal(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans (flat byte intervals)."""
    source, per_text = repeated_spans(docs, length)

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for t, found in zip(b.column(1), b.column(2)):
                t = t.as_py()
                spans = _covered(len(t), found.as_py() or [], length)
                digest, at = hashlib.sha256(), 0
                for x, y in spans:
                    digest.update(t[at:x])
                    at = y
                digest.update(t[at:])
                rows.append((len(t), sum(y - x for x, y in spans), len(spans), digest.hexdigest(), [z for s in spans for z in s]))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)]], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans"])

    joined = source.join(per_text, ["did", "th"], "left").select("doc_id", "text", "runs")
    kind = dict(docs.dtypes)["doc_id"]
    return joined.mapInArrow(out, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<long>")
