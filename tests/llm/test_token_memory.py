"""What a Python worker of the token operators holds at once."""

import sys
import tracemalloc

import pyarrow as pa

from orderdep.llm import common, token_codes, tokens
from orderdep.llm.tokens import tokenizer_path

ROWS, BYTES = (f"spark.sql.execution.arrow.max{x}PerBatch" for x in ("Records", "Bytes"))


def batch_sizes(docs, *_):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_pydict({"n": pa.array([b.num_rows]), "size": pa.array([b.nbytes])})

    return docs.select("doc_id", "text").mapInArrow(sizes, "n long, size long")


def test_texts_come_in_small_batches(spark, monkeypatch):
    monkeypatch.setattr(token_codes, "encode_segments", batch_sizes)
    before = [spark.conf.get(c) for c in (ROWS, BYTES)]
    short = spark.range(0, 5000, 1, 1).selectExpr("id AS doc_id", "'a' AS text")
    long = spark.range(0, 900, 1, 1).selectExpr("id AS doc_id", "repeat('word ', 20000) AS text")
    for docs, rows in ((short, 5000), (long, 900)):
        got = token_codes.written(docs, "", 2).collect()
        assert sum(r["n"] for r in got) == rows
        assert max(r["n"] for r in got) <= 1000 and max(r["size"] for r in got) <= token_codes.BATCH_BYTES + 200_000
    assert [spark.conf.get(c) for c in (ROWS, BYTES)] == before


def test_settings_of_the_session_come_back(spark):
    spark.conf.set(BYTES, "9000000")
    try:
        with common.small_batches(spark, size=1 << 20):
            assert spark.conf.get(BYTES) == "1048576"
        assert spark.conf.get(BYTES) == "9000000"
    finally:
        spark.conf.unset(BYTES)


def test_a_full_generation_fits_its_table():
    """One piece more than two thirds of a power of two doubles the table of a dict."""
    full = dict.fromkeys(map(str, range(tokens.CACHE_PIECES)))
    assert sys.getsizeof(full) < 24 * len(full)


def test_no_third_generation():
    """When a generation is full, the one before is gone before the copy is made."""
    pieces = tokens.TextEncoder(tokenizer_path("word_bpe_49k.json"), 5000).first
    tracemalloc.start()
    try:
        for k in range(10_000):
            pieces[f"w{k}"]
        assert len(pieces) == len(pieces.old) == 5000
        tracemalloc.reset_peak()
        before = tracemalloc.get_traced_memory()[0]
        pieces["one more"]
        more = tracemalloc.get_traced_memory()[1] - before
    finally:
        tracemalloc.stop()
    assert len(pieces) == 1 and len(pieces.old) == 5000 and more < sys.getsizeof(pieces.old) / 4, more
