"""The registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import backoff_lm, decontam, ordinal_quality, packing, pseudonyms, robust_rules, sharding, simhash, suffix_dedup, token_codes
from .common import own, table
from .tokens import tokenizer_path

SQL: dict[str, str] = {}
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document against every benchmark item, windows of 10 words."""
    return decontam.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES["op1_decontamination"] = op1_decontamination
SQL["op1_decontamination"] = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(list_slice(w, i, i + least(len(w), 10) - 1), ' ') AS g
       FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, i, n, array_to_string(list_slice(w, i, i + n - 1), ' ') AS g
       FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, sizes WHERE len(w) >= n)),
m AS (SELECT dw.doc_id, dw.i, dw.n, bw.item_id FROM dw JOIN bw ON dw.g = bw.g AND dw.n = bw.n),
hits AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM m) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, coalesce(hits.n_hit, 0) AS n_hit, coalesce(its.n_items, 0) AS n_items,
       sha256(coalesce(its.ids, '')) AS items_sha256, coalesce(hits.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hits USING (doc_id) LEFT JOIN its USING (doc_id)
"""


def op4_token_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text as directly addressable codes, written, read back and digested."""
    return token_codes.document_digests(token_codes.written(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), 2))


QUERIES["op4_token_codes"] = op4_token_codes


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 1024 byte-level tokens."""
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), 0)


QUERIES["op5_packing"] = op5_packing


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of all documents whose 3-word SimHash fingerprints differ in at most 3 bits."""
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


QUERIES["op9_simhash"] = op9_simhash


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 24 shards of near equal bytes, equal texts together."""
    return sharding.shard(table(spark, sf_dir, "documents"), 24)


QUERIES["op3_sharding"] = op3_sharding


def op10_robust_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base counts of every document and the verdict of its language's and source's robust estimate."""
    found = robust_rules.judged(table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source"), with_text=False)
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "distance")
    return found.select("doc_id", *[F.col(own(n)).alias(n) for n in names])


QUERIES["op10_robust_rules"] = op10_robust_rules


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without the bytes of 200-byte strings that start twice or more in all documents."""
    return suffix_dedup.removal(table(spark, sf_dir, "documents")).drop("spans")


QUERIES["op8_suffix_dedup"] = op8_suffix_dedup
SQL["op8_suffix_dedup"] = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS h, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
w AS (SELECT r, i, md5_number(substring(h, 2 * i - 1, 400)) AS k FROM (SELECT r, h, unnest(range(1, n - 198)) AS i FROM d WHERE n >= 200)),
rep AS (SELECT k FROM w GROUP BY k HAVING count(*) > 1),
s AS (SELECT r, i, CASE WHEN i > lag(i) OVER (PARTITION BY r ORDER BY i) + 200 THEN 1 ELSE 0 END AS fresh FROM w SEMI JOIN rep ON w.k = rep.k),
g AS (SELECT r, sum(fresh) OVER (PARTITION BY r ORDER BY i) AS g, i FROM s),
spans AS (SELECT r, g, min(i) AS a, max(i) + 200 AS b FROM g GROUP BY r, g),
gaps AS (SELECT r, b AS a, lead(a) OVER (PARTITION BY r ORDER BY a) AS b FROM spans UNION ALL SELECT r, 1, min(a) FROM spans GROUP BY r),
kept AS (SELECT r, string_agg(substring(h, 2 * a - 1, 2 * (coalesce(b, n + 1) - a)), '' ORDER BY a) AS h FROM gaps JOIN d USING (r) GROUP BY r),
t AS (SELECT r, sum(b - a) AS n_removed, count(*) AS n_spans FROM spans GROUP BY r)
SELECT d.doc_id, CAST(d.n AS BIGINT) AS n_bytes, CAST(coalesce(t.n_removed, 0) AS BIGINT) AS n_removed, coalesce(t.n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept.h, d.h))) AS kept_sha256
FROM d LEFT JOIN t USING (r) LEFT JOIN kept USING (r)
"""


def op6_backoff_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stupid-backoff score of every document under the trigram, bigram and word counts of all others."""
    found = backoff_lm.scores(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", F.round("log_score", 4).alias("log_score"), F.round("mean_log_score", 6).alias("mean_log_score"))


QUERIES["op6_backoff_lm"] = op6_backoff_lm
SQL["op6_backoff_lm"] = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
t AS (SELECT r, len(w) AS n, w[i] AS w1, CASE WHEN i > 1 THEN w[i - 1] || ' ' || w[i] END AS w2, CASE WHEN i > 2 THEN w[i - 2] || ' ' || w[i - 1] || ' ' || w[i] END AS w3,
             CASE WHEN i > 1 THEN w[i - 1] END AS u1, CASE WHEN i > 2 THEN w[i - 2] || ' ' || w[i - 1] END AS u2
      FROM (SELECT r, w, unnest(range(1, len(w) + 1)) AS i FROM d)),
own AS (SELECT r, g, count(*) AS c FROM (SELECT r, w1 AS g FROM t UNION ALL SELECT r, w2 FROM t UNION ALL SELECT r, w3 FROM t) WHERE g IS NOT NULL GROUP BY r, g),
others AS (SELECT r, g, sum(c) OVER (PARTITION BY g) - c AS f FROM own),
x AS (SELECT t.r, greatest((SELECT count(*) FROM t) - n, 1) AS n, a.f AS f1, b.f AS f2, c.f AS f3, p.f AS c1, q.f AS c2
      FROM t JOIN others AS a ON a.r = t.r AND a.g = w1 LEFT JOIN others AS b ON b.r = t.r AND b.g = w2 LEFT JOIN others AS c ON c.r = t.r AND c.g = w3
             LEFT JOIN others AS p ON p.r = t.r AND p.g = u1 LEFT JOIN others AS q ON q.r = t.r AND q.g = u2),
s AS (SELECT r, count(*) AS n_words, sum(CASE WHEN f3 > 0 THEN ln(f3) - ln(c2) WHEN f2 > 0 THEN ln(f2) - ln(c1) ELSE ln(CASE WHEN f1 > 0 THEN f1 ELSE 0.4 END) - ln(n) END
             + CASE WHEN f3 IS NULL OR f3 > 0 THEN 0 ELSE ln(0.4) END + CASE WHEN f3 > 0 OR f2 IS NULL OR f2 > 0 THEN 0 ELSE ln(0.4) END) AS log_score FROM x GROUP BY r)
SELECT d.doc_id, coalesce(s.n_words, 0) AS n_words, round(coalesce(s.log_score, 0), 4) AS log_score, round(s.log_score / s.n_words, 6) AS mean_log_score
FROM d LEFT JOIN s USING (r)
"""


#: The key of these queries; a real run passes its own, kept secret.
EXAMPLE_KEY = b"example key of the registered queries"


def op2_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with pseudonyms for its personal data and secrets."""
    found = pseudonyms.pseudonymise(table(spark, sf_dir, "documents").select("doc_id", "text"), EXAMPLE_KEY, kinds_col="kinds")
    return found.select("doc_id", "text", F.size("kinds").cast("long").alias("n_replaced"), F.array_join(F.array_sort(F.array_distinct("kinds")), ",").alias("kinds"))


QUERIES["op2_pseudonyms"] = op2_pseudonyms


def op7_ordinal_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grades of all documents by a model of the labels (0 toxic, 1 low quality, 2 good); kept where 1 or 2 is likelier than 0."""
    docs = table(spark, sf_dir, "documents")
    ratings = table(spark, sf_dir, "labels").select("doc_id", ordinal_quality.graded(F.col("quality"), F.col("toxic")).alias("grade"))
    return ordinal_quality.grade(docs, ordinal_quality.train(docs, ratings, 3), tail=1)


QUERIES["op7_ordinal_quality"] = op7_ordinal_quality
