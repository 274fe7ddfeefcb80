"""Queries over the given tables by the operators of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    from . import shared

    shared.small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op9_weak_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import weak_quality

    docs = table(spark, sf_dir, "documents")
    return weak_quality.classify(docs, weak_quality.fit(docs, table(spark, sf_dir, "labels")))


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from . import byte_bpe

    return byte_bpe.digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op1_ngram_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import ngram_lm

    return ngram_lm.score(table(spark, sf_dir, "documents"), F.crc32(F.col("doc_id").cast("string")) % 7 == 2)


def op2_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import dart_dedup

    return dart_dedup.classes(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "class_size")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import language_id

    docs = table(spark, sf_dir, "documents")
    model = language_id.train(docs, fold=5)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    return language_id.predict(docs, model).withColumn("held_out", held)


def op4_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import fingerprints

    return fingerprints.with_edits(table(spark, sf_dir, "documents"))


def op5_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import source_mixing

    mixed = source_mixing.mix(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return mixed.drop("tie")


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import quality_rules, shared

    stats = shared.keep(quality_rules.statistics(table(spark, sf_dir, "documents")), "statistics")
    rules = quality_rules.learn(stats, table(spark, sf_dir, "labels"))
    failed = quality_rules.base_failed()
    return stats.select("doc_id", *quality_rules.COUNTS, failed.alias("base_failed"), (~failed & rules.verdict()).alias("kept"))


def op7_run_length_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import run_length_dedup

    return run_length_dedup.deduplicate(table(spark, sf_dir, "documents"))


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import secret_scan

    return secret_scan.digests(secret_scan.scan(table(spark, sf_dir, "documents")))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_ngram_scores": op1_ngram_scores,
    "op2_near_duplicates": op2_near_duplicates,
    "op3_language_id": op3_language_id,
    "op4_document_fingerprints": op4_document_fingerprints,
    "op5_source_mixing": op5_source_mixing,
    "op6_quality_rules": op6_quality_rules,
    "op7_run_length_dedup": op7_run_length_dedup,
    "op8_secret_scan": op8_secret_scan,
    "op9_weak_quality": op9_weak_quality,
    "op10_byte_bpe": op10_byte_bpe,
}

# -- the columns that SQL can express, of the queries whose other columns it cannot


def ngram_base_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op1_ngram_scores(spark, sf_dir).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", F.round("base_score", 4).alias("base_score"))


def fingerprint_edits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op4_document_fingerprints(spark, sf_dir).select("doc_id", "n_chars", "edited_sha256")


def quality_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op6_quality_rules(spark, sf_dir).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


def secret_base_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op8_secret_scan(spark, sf_dir).drop("spans")


def decoded_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op10_byte_bpe(spark, sf_dir).select("doc_id", "decoded_sha256")


QUERIES |= {f.__name__: f for f in (ngram_base_scores, fingerprint_edits, quality_base_counts, secret_base_spans, decoded_texts)}

_WORD = r"'[^\x20\x09-\x0D]+'"
#: crc32 of doc_id as text: a step for each byte and for each of its bits
_CRC = "xor(list_reduce(list_concat([4294967295::BIGINT], flatten(list_transform(string_split(doc_id::VARCHAR, ''), lambda c: [ascii(c)::BIGINT, -1, -1, -1, -1, -1, -1, -1, -1]))), lambda a, x: CASE WHEN x >= 0 THEN xor(a, x) WHEN a & 1 = 1 THEN xor(a >> 1, 3988292384) ELSE a >> 1 END), 4294967295)"
_VALUE = "[A-Za-z0-9+/_.=-]+"
_KEYWORD = "([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])"
_ASSIGN = _KEYWORD + r"""["'']?\x20*[:=]\x20*["'']?(""" + _VALUE + ")"


def _matches(kind: str, number: int, pattern: str, group: int, least: int) -> str:
    """Places of a pattern's matches: the lengths of what stands between them and of the matches before."""
    lists = f"SELECT doc_id, regexp_extract_all(t, '{pattern}', 0) AS m, regexp_extract_all(t, '{pattern}', {group}) AS v, string_split_regex(t, '{pattern}') AS p FROM docs"
    begin = "list_sum(list_transform(p[1:k], lambda x: length(x)))::BIGINT + coalesce(list_sum(list_transform(m[1:k - 1], lambda x: length(x))), 0)::BIGINT"
    return f"SELECT doc_id, '{kind}' AS kind, {number} AS number, {begin} AS a, length(m[k]) AS size FROM (SELECT *, unnest(range(1, len(m) + 1)) AS k FROM ({lists})) WHERE length(v[k]) >= {least}"


ORACLE_SQL: dict[str, str] = {
    "ngram_base_scores": f"""
WITH docs AS (SELECT doc_id, {_CRC} % 7 = 2 AS held_out, list_append(list_transform(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), {_WORD}), lambda w: 'w' || w), 'end') AS tokens FROM documents),
token AS (SELECT doc_id, held_out, unnest(tokens) AS token FROM docs),
seen AS (SELECT token, count(*) AS c FROM token WHERE NOT held_out GROUP BY 1),
whole AS (SELECT coalesce(sum(c), 0)::BIGINT AS n, count(*) AS v FROM seen)
SELECT doc_id, held_out, count(*) AS n_tokens, count(c) AS n_known, n AS train_tokens, round(sum(log10((coalesce(c, 0) + 1) / (n + v + 1))), 4) AS base_score
FROM token LEFT JOIN seen USING (token), whole GROUP BY doc_id, held_out, n""",
    "op2_near_duplicates": f"""
WITH RECURSIVE texts AS (SELECT coalesce(text, '') AS t, min(doc_id) AS id FROM documents GROUP BY 1),
words AS (SELECT id, regexp_extract_all(t, {_WORD}) AS w FROM texts),
shingle AS (SELECT id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS s FROM words),
counted AS (SELECT id, s, count(*) AS c FROM shingle GROUP BY ALL),
sizes AS (SELECT id, count(*) AS n, sum(c) AS w FROM counted GROUP BY 1),
both_ AS (SELECT a.id AS a, b.id AS b, count(*) AS n, sum(least(a.c, b.c)) AS w FROM counted a JOIN counted b ON a.s = b.s AND a.id < b.id GROUP BY ALL),
link AS (SELECT a, b FROM both_ JOIN sizes x ON x.id = a JOIN sizes y ON y.id = b WHERE 5 * both_.n >= 4 * (x.n + y.n - both_.n) OR 5 * both_.w >= 4 * (x.w + y.w - both_.w)),
edge AS (SELECT a, b FROM link UNION SELECT b, a FROM link),
reach(id, other) AS (SELECT id, id FROM texts UNION SELECT reach.id, edge.b FROM reach JOIN edge ON edge.a = reach.other),
class AS (SELECT id, min(other) AS class_id FROM reach GROUP BY 1),
member AS (SELECT doc_id, class_id FROM documents JOIN texts ON coalesce(text, '') = t JOIN class USING (id))
SELECT doc_id, class_id, count(*) OVER (PARTITION BY class_id) AS class_size FROM member""",
    "fingerprint_edits": """
WITH t AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
n AS (SELECT doc_id, t, length(t)::BIGINT AS n, coalesce(lead(t) OVER (ORDER BY doc_id), first(t) OVER (ORDER BY doc_id)) AS after FROM t)
SELECT doc_id, n AS n_chars, sha256(substr(t, 1, n - n // 4) || substr(after, 1, n // 4)) AS edited_sha256 FROM n""",
    "quality_base_counts": f"""
WITH docs AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), {_WORD}) AS w FROM documents),
line AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM docs),
dup AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n FROM line WHERE regexp_matches(line, {_WORD}) GROUP BY 1),
windows AS (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM docs)),
often AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM windows),
again AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM often, range(0, 8) AS r(k) WHERE c > 1 GROUP BY 1)
SELECT docs.doc_id, len(w) AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
  coalesce(dup.n, 0) AS n_dup_lines, coalesce(again.n, 0) AS n_repeat_words, len(w) < 20 OR 100 * coalesce(again.n, 0) > 30 * len(w) AS base_failed
FROM docs LEFT JOIN dup USING (doc_id) LEFT JOIN again USING (doc_id)""",
    "op7_run_length_dedup": """
WITH docs AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, octet_length(encode(coalesce(text, '')))::BIGINT AS n FROM documents),
part AS (SELECT doc_id, n, j, substr(h, 2000 * j + 1, 2100) AS part FROM (SELECT *, unnest(range(0, (n + 950) // 1000)) AS j FROM docs WHERE n >= 50)),
place AS (SELECT doc_id, 1000 * j + r AS i, substr(part, 2 * r + 1, 100) AS s FROM (SELECT *, unnest(range(0, least(1000, n - 49 - 1000 * j))) AS r FROM part)),
first_ AS (SELECT s, min(doc_id) AS id FROM place GROUP BY s HAVING min(doc_id) < max(doc_id)),
gone AS (SELECT doc_id, i FROM place JOIN first_ USING (s) WHERE id < doc_id),
marked AS (SELECT doc_id, i, CASE WHEN i - lag(i) OVER (PARTITION BY doc_id ORDER BY i) <= 50 THEN 0 ELSE 1 END AS fresh FROM gone),
numbered AS (SELECT doc_id, i, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS k FROM marked),
span AS (SELECT doc_id, k, min(i) AS a, max(i) + 50 AS b FROM numbered GROUP BY ALL),
piece AS (SELECT doc_id, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS c FROM span),
cut AS (SELECT doc_id, sum(b - a)::BIGINT AS n_removed, count(*) AS n_spans, max(b) AS tail, string_agg(substr(h, 2 * c + 1, 2 * (a - c)), '' ORDER BY a) AS kept FROM piece JOIN docs USING (doc_id) GROUP BY 1)
SELECT doc_id, n AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, '') || substr(h, 2 * coalesce(tail, 0) + 1))) AS kept_sha256 FROM docs LEFT JOIN cut USING (doc_id)""",
    "secret_base_spans": f"""
WITH docs AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
span AS ({_matches("assign", 0, _ASSIGN, 2, 12)} UNION ALL {_matches("access", 1, "AKIA[A-Z0-9]+", 0, 18)} UNION ALL {_matches("hex", 2, "[0-9a-f]{16,}", 0, 16)}),
joined AS (SELECT doc_id, count(*) FILTER (number = 0) AS n_assign, count(*) FILTER (number = 1) AS n_access, count(*) FILTER (number = 2) AS n_hex, string_agg(kind || ':' || a || ':' || (a + size), ',' ORDER BY a, number) AS line FROM span GROUP BY 1)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(line, '')) AS base_sha256 FROM docs LEFT JOIN joined USING (doc_id)""",
    "decoded_texts": "SELECT doc_id, sha256(coalesce(text, '')) AS decoded_sha256 FROM documents",
}
