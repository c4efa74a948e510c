"""The registered queries and the pipeline on the smallest tables."""

import collections
import re

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from orderdep.llm import queries
from orderdep.llm.tokens import TextEncoder, tokenizer_path


@pytest.mark.parametrize("name", sorted(queries.QUERIES))
def test_query(spark, sf_dir, name):
    df = queries.QUERIES[name](spark, sf_dir)
    columns = sorted(df.columns)
    rows = sorted(repr(tuple(r)) for r in df.select(*columns).collect())
    assert rows
    if name in queries.SQL:
        con = duckdb.connect()
        for t in ("documents", "benchmark", "labels"):
            con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
        assert rows == sorted(repr(r) for r in con.sql(f"SELECT {', '.join(columns)} FROM ({queries.SQL[name]})").fetchall())


def test_pipeline(spark, sf_dir):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "decontamination", "pseudonyms", "packing"]
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, seen = docs.columns, [docs]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        seen.append(stage(spark, seen[-1], sf_dir).cache())
        assert seen[-1].columns == columns and seen[-1].count() <= seen[-2].count()
    got = corpus_pipeline.STAGES[-1][1](spark, seen[-1], sf_dir).collect()
    e = TextEncoder(tokenizer_path("byte_bpe_50k.json"))
    pieces = collections.defaultdict(list)
    for r in got:
        pieces[r["doc_id"]].append(r)
    for i, text in seen[-1].select("doc_id", "text").collect():
        ids = b"".join(bytes(r["ids"]) for r in sorted(pieces[i], key=lambda r: r["start"]))
        assert np.frombuffer(ids, "<u4").tolist() == [*e.ids(text).tolist(), 0]
    assert len(corpus_pipeline.run(spark, sf_dir).collect()) == len(got)


BENCHMARK_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def passes_base_rules(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    windows = [tuple(words[k : k + 3]) for k in range(len(words) - 2)]
    often = collections.Counter(windows)
    repeated = {k + d for k, w in enumerate(windows) if often[w] > 1 for d in range(3)}
    return len(words) >= 50 and 100 * len(repeated) <= 50 * len(words)


def first_of_each(rows):
    """The smallest id of each group of texts that share 0.8 of their five-word shingles, by all pairs."""
    sets = []
    for i, text in rows:
        words = text.encode().translate(bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))).split()
        sets.append((i, {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))}))
    group = {i: {i} for i, _ in sets}
    for k, (i, a) in enumerate(sets):
        for j, b in sets[:k]:
            if group[i] is not group[j] and len(a & b) >= 0.8 * len(a | b):
                group[i] |= group[j]
                for x in group[j]:
                    group[x] = group[i]
    return {min(g) for g in group.values()}


def without_passages(text, windows):
    """The text without runs of words inside any of the windows; None if these are over half of the words."""
    raw = text.encode()
    lower = bytes(b + 32 if 65 <= b <= 90 else b for b in raw)
    words = list(BENCHMARK_WORD.finditer(lower))
    hit = set()
    for size in {len(w) for w in windows}:
        for k in range(len(words) - size + 1):
            if tuple(m[0] for m in words[k : k + size]) in windows:
                hit.update(range(k, k + size))
    out, at = [], 0
    for k in sorted(hit):
        if k - 1 not in hit:
            out.append(raw[at : words[k].start()])
        at = words[k].end()
    return None if 2 * len(hit) > len(words) else b"".join([*out, raw[at:]]).decode()


def test_first_stages_against_brute_force(spark, sf_dir):
    """Each stage on what its predecessor kept; the outlier verdicts of the first are held elsewhere."""
    stages = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    texts = lambda df: {r["doc_id"]: r["text"] for r in df.select("doc_id", "text").collect()}
    ruled = stages["quality_rules"](spark, docs, sf_dir).cache()
    before, after = texts(docs), texts(ruled)
    assert len(before) == docs.count() and after.items() <= before.items()
    sound = {i for i, t in before.items() if passes_base_rules(t)}
    assert after.keys() <= sound and len(after) >= 0.85 * len(sound)

    single = stages["near_duplicates"](spark, ruled, sf_dir).cache()
    kept = texts(single)
    assert kept.keys() == first_of_each(list(after.items())) and kept.items() <= after.items()

    windows = set()
    for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect():
        words = tuple(BENCHMARK_WORD.findall(bytes(b + 32 if 65 <= b <= 90 else b for b in (r["text"] or "").encode())))
        windows |= {words[k : k + 10] for k in range(max(1, len(words) - 9))} - {()}
    expected = {i: without_passages(t, windows) for i, t in kept.items()}
    cut = texts(stages["decontamination"](spark, single, sf_dir))
    assert cut == {i: t for i, t in expected.items() if t is not None} and cut != kept
