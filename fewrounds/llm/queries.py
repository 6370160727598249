"""Queries over the given tables for the operators of this subpackage, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, html, langid, neardup, pieces, quality, shards, substrings, surrogates, tokencount


def tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_classes(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "copies")


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.dedup(table(spark, sf_dir, "documents")).drop("kept_text")


def substring_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How long the repeated passages get, by doubled window length."""
    return substrings.levels(table(spark, sf_dir, "documents"))


def op3_sentence_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.digest(table(spark, sf_dir, "documents"), tokenizer("piece_bpe_32k.model"))


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.drop("spans", "items")


def op5_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    store, rows = shards.sharded(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.md5("text").alias("text_md5"))


def shard_manifest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The committed shards: name, tier and rows, and whether the manifest's sizes are those of the files."""
    store, rows = shards.sharded(table(spark, sf_dir, "documents"))
    named = spark.createDataFrame([(s.name, s.file, s.tier, s.size) for s in store.shards()], "shard string, file string, tier int, size long")
    held = rows.groupBy(F.concat_ws("/", F.element_at(F.split("_metadata.file_path", "/"), -2), "_metadata.file_name").alias("file")).agg(F.count(F.lit(1)).alias("n_rows"), F.max("_metadata.file_size").alias("bytes"))
    return named.join(held, "file", "left").select("shard", "tier", F.coalesce("n_rows", F.lit(0)).alias("n_rows"), (F.col("size") == F.col("bytes")).alias("size_ok"))


def op6_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages"))


def surrogate_key(spark: SparkSession) -> str:
    """The session's secret, ``fewrounds.surrogates.key``; the public stand-in serves tests and the given tables only."""
    return spark.conf.get("fewrounds.surrogates.key", "public stand-in")


def op7_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return surrogates.counted(table(spark, sf_dir, "documents"), surrogate_key(spark))


def op8_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    held_out = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2, F.lit(False))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return langid.predict(docs, langid.fit(docs.where(~held_out))).withColumn("held_out", held_out)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokencount.count_tokens(table(spark, sf_dir, "documents"), tokenizer("byte_bpe_50k.json"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.measure(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_near_duplicates, op2_substring_dedup, substring_levels, op3_sentence_pieces, op4_decontaminate, op5_shards, shard_manifest, op6_main_text, op7_surrogates, op8_language, op9_token_counts, op10_quality)}


WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

OP1 = rf"""
WITH RECURSIVE d AS (SELECT doc_id, {WORDS} AS w FROM documents),
     n AS (SELECT w, min(doc_id) AS node, count(*) AS copies FROM d WHERE len(w) > 0 GROUP BY w),
     x AS (SELECT node, md5(array_to_string(w[i:i + least(5, len(w)) - 1], ' ')) AS h FROM (SELECT node, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM n)),
     s AS (SELECT node, h, row_number() OVER (PARTITION BY node, h) AS c, count(*) OVER (PARTITION BY node) AS size FROM x),
     p AS (SELECT a.node AS a, b.node AS b FROM s a JOIN s b ON a.h = b.h AND a.c = b.c AND a.node < b.node GROUP BY a.node, b.node, a.size, b.size HAVING count(*) >= 0.8 * (a.size + b.size - count(*))),
     e AS (SELECT a, b FROM p UNION ALL SELECT b, a FROM p),
     r AS (SELECT a AS node, a AS seen FROM e UNION SELECT r.node, e.b FROM r JOIN e ON r.seen = e.a),
     l AS (SELECT node, min(seen) AS label FROM r GROUP BY node)
SELECT d.doc_id, coalesce(label, n.node, d.doc_id) AS class_id, coalesce(copies, 1)::BIGINT AS copies
FROM d LEFT JOIN n ON d.w = n.w LEFT JOIN l ON n.node = l.node
"""

OP2 = rf"""
WITH d AS (SELECT doc_id, {WORDS} AS w FROM documents),
     p AS (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM d WHERE len(w) >= 13),
     x AS (SELECT doc_id, i, md5(array_to_string(w[i:i + 12], ' ')) AS h FROM p),
     f AS (SELECT h, min(doc_id) AS first FROM x GROUP BY h),
     g AS (SELECT DISTINCT x.doc_id, unnest(range(i, i + 13)) AS pos FROM x JOIN f USING (h) WHERE first < x.doc_id),
     t AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS pos FROM d),
     k AS (SELECT t.doc_id, count(*) AS n_kept, string_agg(word, ' ' ORDER BY pos) AS kept FROM t ANTI JOIN g ON t.doc_id = g.doc_id AND t.pos = g.pos GROUP BY t.doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n_kept, 0))::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN k ON d.doc_id = k.doc_id
"""

LEVELS = rf"""
WITH RECURSIVE d AS (SELECT doc_id, {WORDS} AS w FROM documents),
     x AS (SELECT doc_id, i, md5(array_to_string(w[i:i + 12], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM d WHERE len(w) >= 13)),
     r AS (SELECT 13 AS length, doc_id, i, h FROM (SELECT *, min(doc_id) OVER (PARTITION BY h) < max(doc_id) OVER (PARTITION BY h) AS again FROM x) WHERE again
           UNION ALL
           SELECT length, doc_id, i, h FROM (SELECT *, min(doc_id) OVER (PARTITION BY h) < max(doc_id) OVER (PARTITION BY h) AS again
                                             FROM (SELECT 2 * a.length AS length, a.doc_id, a.i, md5(a.h || b.h) AS h FROM r a JOIN r b ON a.doc_id = b.doc_id AND b.i = a.i + a.length)) WHERE again)
SELECT length, count(DISTINCT doc_id) AS n_docs, count(*) AS n_windows FROM r GROUP BY length
"""

FOLDED = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP4 = rf"""
WITH d AS (SELECT doc_id, {FOLDED} AS w FROM documents),
     b AS (SELECT DISTINCT item_id::VARCHAR AS k, {FOLDED} AS w FROM benchmark WHERE item_id IS NOT NULL),
     bw AS (SELECT DISTINCT k, n, array_to_string(w[i:i + n - 1], ' ') AS g
            FROM (SELECT k, w, least(10, len(w)) AS n, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
     n AS (SELECT DISTINCT n FROM bw),
     x AS (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS g
           FROM (SELECT doc_id, w, n.n AS n, unnest(range(1, len(w) - n.n + 2)) AS i FROM d, n WHERE len(w) >= n.n)),
     m AS (SELECT x.doc_id, x.n, x.i, bw.k FROM x JOIN bw ON x.n = bw.n AND x.g = bw.g),
     h AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS pos FROM m) GROUP BY doc_id),
     s AS (SELECT doc_id, count(*) AS n_items, string_agg(k, ',' ORDER BY k) AS items FROM (SELECT DISTINCT doc_id, k FROM m) GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h ON d.doc_id = h.doc_id LEFT JOIN s ON d.doc_id = s.doc_id
"""


def _op10() -> str:
    lengths = sorted(quality.NGRAM_LIMITS)
    passes = " AND ".join(f"100 * coalesce(dup_chars_{k}, 0) <= {quality.NGRAM_LIMITS[k]} * word_chars" for k in lengths)
    sums = ", ".join(f"sum(chars) FILTER (n = {k}) AS dup_chars_{k}" for k in lengths)
    shown = ", ".join(f"coalesce(dup_chars_{k}, 0)::BIGINT AS dup_chars_{k}" for k in lengths)
    return rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, {WORDS} AS w FROM documents),
     x AS (SELECT doc_id, n, i, md5(array_to_string(w[i:i + n - 1], ' ')) AS h
           FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, (VALUES {", ".join(f"({k})" for k in lengths)}) v(n) WHERE len(w) >= n)),
     r AS (SELECT doc_id, n, i FROM x QUALIFY count(*) OVER (PARTITION BY doc_id, n, h) > 1),
     c AS (SELECT DISTINCT doc_id, n, unnest(range(i, i + n)) AS pos FROM r),
     t AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS pos FROM d),
     g AS (SELECT doc_id, count(*) FILTER (n = 5) AS n_repeat_words, {sums} FROM (SELECT c.doc_id, n, length(word) AS chars FROM c JOIN t ON c.doc_id = t.doc_id AND c.pos = t.pos) GROUP BY doc_id),
     l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM d),
     e AS (SELECT doc_id, line FROM l WHERE regexp_matches(line, '[^\x20\x09-\x0D]') QUALIFY row_number() OVER (PARTITION BY doc_id, line ORDER BY pos) > 1),
     q AS (SELECT doc_id, count(*) AS n_dup_lines, sum(length(regexp_replace(line, '[\x20\x09-\x0D]+', '', 'g'))) AS dup_line_chars FROM e GROUP BY doc_id),
     z AS (SELECT d.doc_id, len(w) AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g')) AS word_chars, length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols,
                  coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(dup_line_chars, 0) AS dup_line_chars, g.* EXCLUDE (doc_id, n_repeat_words)
           FROM d LEFT JOIN g ON d.doc_id = g.doc_id LEFT JOIN q ON d.doc_id = q.doc_id)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words,
       (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed,
       NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND 100 * dup_line_chars <= 30 * word_chars AND {passes} AS kept,
       dup_line_chars::BIGINT AS dup_line_chars, {shown}
FROM z
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_near_duplicates": OP1, "op2_substring_dedup": OP2, "substring_levels": LEVELS, "op4_decontaminate": OP4, "op5_shards": "SELECT doc_id, octet_length(encode(text))::BIGINT AS n_bytes, md5(text) AS text_md5 FROM documents", "op10_quality": _op10()}
