"""Registered queries of the store, and their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import baselines, factorize, measures, retrieval, semistatic, suffix
from ..operators import collection as col
from ..operators import dictionary as dic
from ..operators.codecs import GRID, PAIR_CODECS
from ..session import cut, shared_folder, tasks_for
from ..sources import datasource, store
from ..sources.tables import load
from . import inputs

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def scratch(spark: SparkSession, what: str) -> str:
    """A new folder that driver and executors see."""
    return f"{shared_folder(spark).removeprefix('file://').removeprefix('file:').rstrip('/')}/drstore-{what}-{uuid.uuid4().hex}"


def digest(bodies: DataFrame) -> DataFrame:
    return bodies.select("doc_id", F.md5("body").alias("digest"))


DOC_DIGEST = "SELECT doc_id, md5(text) AS digest FROM documents"
PAGE_DIGEST = "SELECT page_id AS doc_id, md5(html) AS digest FROM pages"

# -- collections

_PLACES = "SELECT {id} AS doc_id, row_number() OVER (ORDER BY {by}) - 1 AS ord, CAST(sum(b) OVER (ORDER BY {by} ROWS UNBOUNDED PRECEDING) - b AS BIGINT) AS start_off, b AS n_bytes FROM (SELECT *, octet_length(encode({text})) AS b FROM {table})"


@query("collection_offsets", _PLACES.format(id="doc_id", by="doc_id", text="text", table="documents"))
def _offsets(spark, sf):
    return inputs.placed(spark, sf, "documents").select("doc_id", "ord", "start_off", "n_bytes")


@query("url_order_offsets", _PLACES.format(id="page_id", by="url, page_id", text="html", table="pages"))
def _url_offsets(spark, sf):
    return inputs.placed(spark, sf, "pages", "url").select("doc_id", "ord", "start_off", "n_bytes")


@query("shuffled_order_offsets", _PLACES.format(id="doc_id", by="md5('0:' || doc_id), doc_id", text="text", table="documents"))
def _shuffled_offsets(spark, sf):
    return inputs.placed(spark, sf, "documents", "shuffled").select("doc_id", "ord", "start_off", "n_bytes")


_BY_HOST = "array_to_string(list_reverse(string_split(regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1), '.')), '.') || '/' || regexp_extract(url, '^[a-z]+://[^/?#]*([^#]*)', 1), page_id"


@query("host_order_documents", _PLACES.format(id="page_id", by=_BY_HOST, text="html", table="pages"))
def _host_order(spark, sf):
    return inputs.placed(spark, sf, "pages", "host").select("doc_id", "ord", "start_off", "n_bytes")


@query(
    "prefix_cut",
    f"WITH p AS ({_PLACES.format(id='doc_id', by='doc_id', text='text', table='documents')}), n AS (SELECT CAST(floor(sum(n_bytes) * 10 / 100) AS BIGINT) AS lim FROM p) SELECT doc_id, start_off, least(n_bytes, lim - start_off) AS n_bytes FROM p, n WHERE start_off < lim",
)
def _prefix(spark, sf):
    return col.prefix(inputs.placed(spark, sf, "documents"), 10).select("doc_id", "start_off", "n_bytes")


@query("folded_conversations", "SELECT conv_id AS doc_id, md5(string_agg(coalesce(text, ''), chr(10) ORDER BY turn, text)) AS digest FROM conversations GROUP BY conv_id")
def _fold(spark, sf):
    return digest(col.fold(load(spark, sf, "conversations"), "conv_id", "turn", "text"))


@query("record_documents", "SELECT o_orderkey AS doc_id, o_orderstatus AS status, count(l_orderkey) AS lines FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY ALL")
def _records(spark, sf):
    docs = col.record_docs(load(spark, sf, "orders"), load(spark, sf, "lineitem"))
    parsed = F.from_json(F.decode("body", "UTF-8"), "status string, lines array<struct<l_linenumber:int>>")
    return docs.select("doc_id", parsed.alias("j")).select("doc_id", F.col("j.status").alias("status"), F.size("j.lines").cast("long").alias("lines"))


# -- dictionaries

_N = "(SELECT sum(octet_length(encode(text))) FROM documents)"


@query(
    "even_sample_positions",
    f"WITH n AS (SELECT CAST({_N} AS HUGEINT) AS n), c AS (SELECT n, CAST(floor(floor(n * 2 / 100) / 512) AS HUGEINT) AS c FROM n) SELECT CAST(k AS BIGINT) AS k, CAST((k * n) // c AS BIGINT) AS start, CAST(least(512, n - (k * n) // c) AS BIGINT) AS n_bytes FROM c, range(0, CAST((SELECT c FROM c) AS BIGINT)) AS r(k)",
)
def _even_positions(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    n = col.total_bytes(p)
    return dic.even_samples(p, n * 2 // 100, 512, n).select("k", "start", F.octet_length("bytes").cast("long").alias("n_bytes"))


#: all documents as one string of hexadecimal digits, two a byte
_WHOLE = "WITH w AS (SELECT string_agg(hex(encode(text)), '' ORDER BY doc_id) AS x FROM documents), n AS (SELECT x, length(x) // 2 AS n FROM w)"


@query("even_sample_bytes", _WHOLE + ", c AS (SELECT x, n, (n * 2 // 100) // 512 AS c FROM n) SELECT k, k * n // c AS start, md5(unhex(substr(x, CAST(2 * (k * n // c) + 1 AS BIGINT), 1024))) AS digest FROM c, range(0, (SELECT c FROM c)) AS r(k)")
def _even_bytes(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    n = col.total_bytes(p)
    return dic.even_samples(p, n * 2 // 100, 512, n).select("k", "start", F.md5("bytes").alias("digest"))


def _bytes_as_text(digits: str) -> str:
    """SQL of a string with one character for each byte, so that its functions count bytes."""
    return f"array_to_string(list_transform(range(0, length({digits}) // 2), lambda i: chr(CAST('0x' || substr({digits}, 2 * i + 1, 2) AS INT))), '')"


_DICT = _WHOLE + ", c AS (SELECT x, n, 2048 // 256 AS c FROM n), dx AS (SELECT string_agg(substr(x, CAST(2 * (k * n // c) + 1 AS BIGINT), 512), '' ORDER BY k) AS dx FROM c, range(0, 8) AS r(k)), d AS (SELECT dx, " + _bytes_as_text("dx") + " AS d FROM dx)"


@query("dictionary_md5", _DICT + " SELECT CAST(length(d) AS BIGINT) AS m, md5(unhex(dx)) AS digest FROM d")
def _dictionary_md5(spark, sf):
    d = inputs.little_dictionary(spark, sf)
    return spark.createDataFrame([(len(d.data), d.md5)], "m long, digest string")


_PIECES = "SELECT ord AS k, start_off AS start, least(n_bytes, 20000 - start_off) AS n_bytes FROM ({}) WHERE start_off < 20000"


@query("random_document_dictionary", _PIECES.format(_PLACES.format(id="doc_id", by="md5('0:' || doc_id), doc_id", text="text", table="documents")))
def _random_documents(spark, sf):
    return dic.random_documents(inputs.documents(spark, sf), 20000).select("k", "start", F.octet_length("bytes").cast("long").alias("n_bytes"))


@query("head_dictionary", _PIECES.format(_PLACES.format(id="doc_id", by="doc_id", text="text", table="documents")))
def _head(spark, sf):
    return dic.head(inputs.placed(spark, sf, "documents"), 20000).select("k", "start", F.octet_length("bytes").cast("long").alias("n_bytes"))


@query("dictionary_versions", f"SELECT doc_id, md5(text) AS digest, CAST(CASE WHEN doc_id % 10 < 7 THEN 0 ELSE 1 END AS INT) AS dict_version FROM documents")
def _versions(spark, sf):
    """Documents of version 0 are still read after the dictionary grew by samples of the others."""
    old, new = inputs.documents(spark, sf).where("doc_id % 10 < 7"), inputs.documents(spark, sf).where("doc_id % 10 >= 7")
    d0 = inputs.dictionary(col.with_offsets(old), 2.0)
    d1 = dic.extend(d0, col.with_offsets(new), 8192, 512)
    enc = factorize.encode(old, d0, "ZV").unionByName(factorize.encode(new, d1, "ZV"))
    return factorize.decode_encoded(enc, d1, carry=("dict_version",)).select("doc_id", F.md5("body").alias("digest"), "dict_version")


@query("pruned_dictionary_roundtrip", DOC_DIGEST)
def _pruned(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    d = dic.prune_and_refill(p, inputs.dictionary(p, 1.0), 1, 512)[-1][1]
    return digest(factorize.decode_encoded(factorize.encode(p, d, "ZV"), d))


# -- suffixes

_SUFFIXES = _DICT + " SELECT row_number() OVER (ORDER BY substr(d, p)) - 1 AS rank, p - 1 AS pos FROM d, range(1, 2049) AS r(p)"


@query("suffix_array_distributed", _SUFFIXES)
def _suffix_df(spark, sf):
    return suffix.suffix_array_df(spark, inputs.little_dictionary(spark, sf).data)


@query("suffix_array_local", _SUFFIXES)
def _suffix_local(spark, sf):
    sa = inputs.little_dictionary(spark, sf).sa
    return spark.createDataFrame(pa.table({"rank": np.arange(len(sa)), "pos": sa.astype(np.int64)}))


@query("substring_occurrences", _DICT + ", q AS (SELECT DISTINCT substr(d, k * 37 + 1, 3) AS pattern FROM d, range(0, 50) AS r(k)) SELECT pattern, (SELECT count(*) FROM range(1, 2047) AS r(p) WHERE substr(d, p, 3) = pattern) AS n FROM q, d")
def _occurrences(spark, sf):
    d = inputs.little_dictionary(spark, sf)
    s = suffix.Searcher(d.data, d.sa)
    words = sorted({d.data[k * 37 : k * 37 + 3] for k in range(50)})
    return spark.createDataFrame([(w.decode("latin-1"), s.occurrences(w)) for w in words], "pattern string, n long")


@query("gram_index", _DICT + " SELECT substr(dx, 2 * p - 1, 8) AS gram, count(*) AS n, min(p) - 1 AS first FROM d, range(1, 2046) AS r(p) GROUP BY 1")
def _gram_index(spark, sf):
    return suffix.gram_index_df(spark, inputs.little_dictionary(spark, sf).data, 4).select("gram", F.size("places").cast("long").alias("n"), F.array_min("places").cast("long").alias("first"))


# -- factors

#: the factors of the whole benchmark table, whose texts are short, relative to the little dictionary of documents
_FACTORS = (
    _DICT.replace("WITH w", "WITH RECURSIVE w", 1)
    + """, s AS (SELECT doc_id, """ + _bytes_as_text("h") + """ AS text FROM (SELECT item_id AS doc_id, hex(encode(text)) AS h FROM benchmark WHERE text <> '')),
f AS (
  SELECT doc_id, text, 1 AS i, 0 AS seq, coalesce(list_max(list_filter(range(1, length(text) + 1), lambda k: contains(d, substr(text, 1, k)))), 0) AS len FROM s, d
  UNION ALL
  SELECT doc_id, text, i + greatest(len, 1), seq + 1, coalesce(list_max(list_filter(range(1, length(text) - (i + greatest(len, 1)) + 2), lambda k: contains(d, substr(text, i + greatest(len, 1), k)))), 0)
  FROM f, d WHERE i + greatest(len, 1) <= length(text)
)"""
)
_POSITIONS = "CAST(CASE WHEN len = 0 THEN ascii(substr(text, i, 1)) ELSE (SELECT arg_min(p, substr(d, p)) - 1 FROM range(1, 2049) AS r(p) WHERE substr(d, p, len) = substr(text, i, len)) END AS BIGINT)"


def _benchmark_factors(spark, sf):
    d = inputs.little_dictionary(spark, sf)
    return d, factorize.factorize(inputs.benchmark(spark, sf), d)


def _all_factors(spark, sf, **spec):
    """Of all documents, whole and in bytes, as the queries without ``benchmark`` have them."""
    p = inputs.placed(spark, sf, "documents")
    d = dic.build(p, dic.DictSpec(**spec)) if spec else inputs.dictionary(p)
    return d, factorize.factorize(p, d)


@query("factor_lengths_benchmark", _FACTORS + " SELECT doc_id, CAST(seq AS INT) AS seq, CAST(i - 1 AS BIGINT) AS doc_off, CAST(len AS INT) AS len FROM f")
def _factor_lengths(spark, sf):
    return factorize.factors_long(_benchmark_factors(spark, sf)[1]).select("doc_id", "seq", "doc_off", "len")


@query(
    "factor_positions_benchmark",
    _FACTORS + f" SELECT f.doc_id, CAST(f.seq AS INT) AS seq, {_POSITIONS} AS pos FROM f, d",
)
def _factor_positions(spark, sf):
    return factorize.factors_long(_benchmark_factors(spark, sf)[1]).select("doc_id", "seq", "pos")


# the steps of the worked example, on the dictionary of documents and all benchmark texts; places and ranks are 1-based


@query("worked_example_suffixes", _DICT + ", r AS (SELECT CAST(row_number() OVER (ORDER BY substr(d, p)) AS INT) AS i, CAST(p AS INT) AS suffix FROM d, range(1, 2049) AS r(p)) SELECT r.i, r.suffix, s.i AS inverse FROM r JOIN r AS s ON s.suffix = r.i")
def _example_suffixes(spark, sf):
    """With the inverse beside it."""
    sa = inputs.little_dictionary(spark, sf).sa
    return spark.createDataFrame(pa.table({"i": np.arange(1, len(sa) + 1, dtype=np.int32), "suffix": (sa + 1).astype(np.int32), "inverse": (suffix.rank_array(sa) + 1).astype(np.int32)}))


def _on_benchmark(spark, sf, function: str) -> str:
    """Registers a table function of the little dictionary, and the benchmark texts as a view; FROM clause."""
    spark.udtf.register(function, udfs.for_dictionary(spark, inputs.little_dictionary(spark, sf))[function])
    inputs.benchmark(spark, sf).createOrReplaceTempView("drstore_benchmark")
    return f"FROM drstore_benchmark AS t, LATERAL {function}(t.body) AS f"


@query(
    "worked_example_trace",
    _FACTORS + ", g AS (SELECT doc_id, text, CAST(k AS INT) AS j, k <= len AS found FROM f, range(1, 2049) AS r(k) WHERE i = 1 AND k <= least(len + 1, length(text))), h AS (SELECT doc_id, j, found, (SELECT count(*) FROM range(1, 2049) AS r(p) WHERE substr(d, p) < substr(text, 1, j)) AS below, (SELECT count(*) FROM range(1, 2049) AS r(p) WHERE substr(d, p, j) = substr(text, 1, j)) AS n FROM g, d) SELECT doc_id, j, CAST(CASE WHEN found THEN below + 1 END AS INT) AS lb, CAST(CASE WHEN found THEN below + n END AS INT) AS rb FROM h",
)
def _example_trace(spark, sf):
    return spark.sql(f"SELECT t.doc_id, CAST(f.j + 1 AS INT) AS j, CAST(f.lb + 1 AS INT) AS lb, CAST(f.rb + 1 AS INT) AS rb {_on_benchmark(spark, sf, 'refine_trace')}")


@query("worked_example_factors", _FACTORS + f" SELECT f.doc_id, CAST(f.seq AS INT) AS seq, CAST({_POSITIONS} + CAST(len > 0 AS INT) AS INT) AS pos, CAST(len AS INT) AS len FROM f, d")
def _example_factors(spark, sf):
    return spark.sql(f"SELECT t.doc_id, f.seq, CAST(f.pos + IF(f.len > 0, 1, 0) AS INT) AS pos, f.len {_on_benchmark(spark, sf, 'drf_factors')}")


_VB = "(1 + CAST({v} >= 128 AS INT) + CAST({v} >= 16384 AS INT) + CAST({v} >= 2097152 AS INT) + CAST({v} >= 268435456 AS INT))"


@query("enc_ratio_uv_benchmark", _FACTORS + f", g AS (SELECT count(*) AS n_factors, CAST(sum(4 + {_VB.format(v='len')}) AS BIGINT) AS enc_bytes FROM f) SELECT n_factors, enc_bytes, (SELECT CAST(sum(length(text)) AS BIGINT) FROM s) AS raw_bytes FROM g")
def _uv_small(spark, sf):
    d = inputs.little_dictionary(spark, sf)
    enc = factorize.encode(inputs.benchmark(spark, sf), d, "UV")
    return enc.agg(F.sum("n_factors").alias("n_factors"), F.sum(F.octet_length("pos_stream") + F.octet_length("len_stream")).alias("enc_bytes"), F.sum("n_bytes").alias("raw_bytes"))


@query("avg_factor_len_benchmark", _FACTORS + " SELECT round(sum(greatest(len, 1)) / count(*), 9) AS avg_factor_len, round(avg(CASE WHEN len > 0 THEN len END), 9) AS avg_match_len, round(avg(CASE WHEN len = 0 THEN 1.0 ELSE 0.0 END), 9) AS literal_share, count(DISTINCT CASE WHEN len = 0 THEN substr(text, i, 1) END) AS absent_bytes, round(avg(CAST(len < 100 AS INT)), 9) AS under_100, round(avg(CAST(len <= 256 AS INT)), 9) AS up_to_sample, round(avg(CAST(len < 128 AS INT)), 9) AS one_byte FROM f")
def _avg_small(spark, sf):
    s = measures.length_stats(_benchmark_factors(spark, sf)[1], 256)
    return s.select("absent_bytes", *(F.round(c, 9).alias(c) for c in ("avg_factor_len", "avg_match_len", "literal_share", "under_100", "up_to_sample", "one_byte")))


@query("position_skew_benchmark", _FACTORS + f", g AS (SELECT doc_id, len, {_POSITIONS} AS pos FROM f, d WHERE len > 0), b AS (SELECT doc_id, count(*) AS n, count(DISTINCT pos) AS u, count(DISTINCT (pos, len)) AS p FROM g GROUP BY 1) SELECT CAST(sum(n) AS BIGINT) AS n_matches, round(sum(u) / sum(n), 9) AS distinct_in_documents, round(1 - sum(p) / sum(n), 9) AS repeated_pairs_in_documents, round((SELECT count(DISTINCT pos) / count(*) FROM g), 9) AS distinct_overall FROM b")
def _skew_benchmark(spark, sf):
    s = measures.position_skew(_benchmark_factors(spark, sf)[1])
    return s.select("n_matches", *(F.round(c, 9).alias(c) for c in ("distinct_in_documents", "repeated_pairs_in_documents", "distinct_overall")))


@query("length_histogram_benchmark", _FACTORS + " SELECT CAST(CASE WHEN len < 100 THEN len ELSE len // 10 * 10 END AS BIGINT) AS bin, count(*) AS cnt FROM f GROUP BY 1")
def _histogram_small(spark, sf):
    return measures.histogram(_benchmark_factors(spark, sf)[1])


_USED = _FACTORS + ", g AS (SELECT DISTINCT substr(text, i, len) AS w, len FROM f WHERE len > 0), h AS (SELECT arg_min(p, substr(d, p)) AS p, any_value(len) AS len FROM g, d, range(1, 2049) AS r(p) WHERE substr(d, p, len) = w GROUP BY w), u AS (SELECT count(DISTINCT p + k) AS used FROM h, range(0, 400) AS r(k) WHERE k < len) SELECT CAST(2048 AS BIGINT) AS m, used AS used_bytes, round(100.0 * (2048 - used) / 2048, 6) AS unused_pct FROM u"


@query("unused_pct_benchmark", _USED)
def _unused_small(spark, sf):
    d, f = _benchmark_factors(spark, sf)
    return measures.unused_pct(f, len(d.data)).withColumn("unused_pct", F.round("unused_pct", 6))


@query("unused_pct_bitmap_benchmark", _USED)
def _unused_bitmap(spark, sf):
    d, f = _benchmark_factors(spark, sf)
    return measures.unused_pct_bitmap(f, len(d.data)).withColumn("unused_pct", F.round("unused_pct", 6))


@query("mergeable_factors", "SELECT CAST(NULL AS BIGINT) AS doc_id, CAST(NULL AS INT) AS seq WHERE false")
def _mergeable(spark, sf):
    """Greedy factors that lie next to each other in the dictionary would be one factor: there are none."""
    return factorize.mergeable(_all_factors(spark, sf)[1])


# the same over all documents; SQL would be too slow for the factors themselves


@query("factor_lengths")
def _all_lengths(spark, sf):
    return factorize.factors_long(_all_factors(spark, sf)[1]).select("doc_id", "seq", "doc_off", "len")


@query("factor_positions")
def _all_positions(spark, sf):
    return factorize.factors_long(_all_factors(spark, sf)[1]).select("doc_id", "seq", "pos")


@query("enc_ratio_uv")
def _uv(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    enc = factorize.encode(p, inputs.dictionary(p), "UV")
    return enc.agg(F.sum("n_factors").alias("n_factors"), F.sum(F.octet_length("pos_stream") + F.octet_length("len_stream")).alias("enc_bytes"), F.sum("n_bytes").alias("raw_bytes"))


@query("avg_factor_len")
def _avg(spark, sf):
    return measures.length_stats(_all_factors(spark, sf)[1], 512).select("avg_factor_len", "avg_match_len", "literal_share")


@query("length_histogram")
def _histogram(spark, sf):
    return measures.histogram(_all_factors(spark, sf)[1])


@query("unused_pct")
def _unused(spark, sf):
    d, f = _all_factors(spark, sf)
    return measures.unused_pct(f, len(d.data))


@query("unused_pct_bitmap")
def _unused_all_bitmap(spark, sf):
    d, f = _all_factors(spark, sf)
    return measures.unused_pct_bitmap(f, len(d.data))


@query("decode_builtin", DOC_DIGEST)
def _decode_builtin(spark, sf):
    """The dictionary is a literal of at most 64 KB; the documents are all."""
    d, f = _all_factors(spark, sf, m_bytes=1 << 15, s=512)
    return digest(factorize.decode_sql(f, d))


@query("factors_leftmost_roundtrip", DOC_DIGEST)
def _leftmost(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    d = inputs.dictionary(p, 1.0)
    return digest(factorize.decode(factorize.factorize(p, d, "leftmost"), d))


@query("factors_without_boundaries_roundtrip", DOC_DIGEST)
def _stream_factors(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    d = inputs.dictionary(p, 1.0)
    return digest(factorize.decode(factorize.factorize_stream(p, d), d))


# -- round trips


def _roundtrip(codec: str, name: str, order: str = "natural") -> Query:
    def run(spark, sf):
        p = inputs.placed(spark, sf, name, order)
        d = inputs.dictionary(p)
        return digest(factorize.decode_encoded(factorize.encode(p, d, codec), d))

    return run


for _codec in (*PAIR_CODECS, "Zi", "US", "UP", "FV"):
    for _name, _sql in (("documents", DOC_DIGEST), ("pages", PAGE_DIGEST)):
        if _codec in PAIR_CODECS or _name == "documents":
            query(f"roundtrip_{_codec}_{_name}", _sql)(_roundtrip(_codec, _name))
query("roundtrip_ZZ_pages_url_order", PAGE_DIGEST)(_roundtrip("ZZ", "pages", "url"))


@query("roundtrip_codec_grid", f"SELECT codec, doc_id, md5(text) AS digest FROM documents, (VALUES {', '.join(f'({c!r})' for c in GRID)}) AS t(codec)")
def _all_grid(spark, sf):
    return _codecs(*_all_factors(spark, sf))


def _codecs(d, f):
    out = None
    for c in GRID:
        part = factorize.decode_encoded(factorize.recode(f, c), d).select(F.lit(c).alias("codec"), "doc_id", F.md5("body").alias("digest"))
        out = part if out is None else out.unionByName(part)
    return out


def _blocked(name: str, size: int) -> Query:
    def run(spark, sf):
        return digest(baselines.read_all_blocked(baselines.blocked_store(inputs.placed(spark, sf, "documents"), name, size), name))

    return run


for _name in ("raw", "zlib", "lzma"):
    for _size in (0, 100_000, 1_000_000):
        query(f"roundtrip_{_name}_{_size // 1000}k", DOC_DIGEST)(_blocked(_name, _size))
for _name in ("gzip", "deflate9", "deflate14", "lzma-128"):
    query(f"roundtrip_{_name.replace('-', '_window_')}_200k", DOC_DIGEST)(_blocked(_name, 200_000))


@query("two_pass_roundtrip", PAGE_DIGEST)
def _two_pass(spark, sf):
    return digest(baselines.open_two_pass(baselines.two_pass_store(load(spark, sf, "pages"))))


@query("primed_deflate_roundtrip", DOC_DIGEST)
def _primed(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    d = inputs.dictionary(p).data
    return digest(baselines.open_primed(baselines.primed(p, d), d))


def _each(spark, sf, f: Callable[[bytes], bytes]) -> DataFrame:
    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([f(x) for x in b.column(1).to_pylist()], pa.binary())], names=["doc_id", "body"])

    rows = inputs.documents(spark, sf)
    return digest(rows.repartition(tasks_for(rows)).select("doc_id", "body").mapInArrow(run, "doc_id long, body binary"))


@query("window_lz_roundtrip", DOC_DIGEST)
def _window_lz(spark, sf):
    from ..operators.lz import undo_window_lz, window_lz

    return _each(spark, sf, lambda x: undo_window_lz(window_lz(x)))


@query("pair_grammar_roundtrip", DOC_DIGEST)
def _grammar(spark, sf):
    from ..operators.lz import pair_grammar, undo_pair_grammar

    return _each(spark, sf, lambda x: undo_pair_grammar(*pair_grammar(x, 40)))


@query("end_aligned_lz_roundtrip", DOC_DIGEST)
def _end_aligned(spark, sf):
    from ..operators.lz import end_aligned, open_end_aligned

    return _each(spark, sf, lambda x: open_end_aligned(end_aligned(x), 0, len(x)))


@query("dynamic_dense_roundtrip", DOC_DIGEST)
def _dynamic(spark, sf):
    import re

    def both(x: bytes) -> bytes:
        words = re.findall(r"\w+|\W+", x.decode())
        plain = semistatic.undo_dynamic_dense(semistatic.dynamic_dense(words))
        light = semistatic.undo_dynamic_dense(semistatic.dynamic_dense(words, True), True)
        return "".join(plain).encode() if plain == light else b"differs"

    return _each(spark, sf, both)


@query("decode_range", "SELECT doc_id, md5(unhex(substr(hex(encode(text)), 2 * (octet_length(encode(text)) // 3) + 1, 128))) AS digest FROM documents")
def _range(spark, sf):
    p = inputs.documents(spark, sf)
    d = inputs.little_dictionary(spark, sf)
    enc = factorize.encode(p, d, "ZV").withColumn("start", F.floor(F.col("n_bytes") / 3)).withColumn("size", F.lit(64))
    return factorize.decode_slices(enc, d).select("doc_id", F.md5("part").alias("digest"))


@query("snippet", "SELECT doc_id, CAST(position('ing' IN lower(text)) AS INT) AS at, substr(text, greatest(1, position('ing' IN lower(text)) - 20), position('ing' IN lower(text)) - greatest(1, position('ing' IN lower(text)) - 20) + 23) AS snippet FROM documents WHERE contains(lower(text), 'ing')")
def _snippet(spark, sf):
    """From the encoded store."""
    _, d, path = _written(spark, sf)
    return store.snippet(store.decode_all(store.read_store(spark, path), d), "ing", 20)


# -- sizes in closed form


@query("stream_size_u", "SELECT l_returnflag, CAST(4 * count(*) AS BIGINT) AS n_bytes FROM lineitem GROUP BY 1")
def _size_u(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.sum(measures.u_size(F.col("l_orderkey"))).cast("long").alias("n_bytes"))


@query("stream_size_v", f"SELECT l_returnflag, CAST(sum({_VB.format(v='l_orderkey')}) AS BIGINT) AS n_bytes FROM lineitem GROUP BY 1")
def _size_v(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.sum(measures.vbyte_size(F.col("l_orderkey"))).cast("long").alias("n_bytes"))


@query("vbyte_functions", f"SELECT l_orderkey, CAST(sum({_VB.format(v='l_partkey')}) AS INT) AS n_bytes, CAST(sum(l_partkey) AS BIGINT) AS total FROM lineitem GROUP BY 1")
def _vbyte(spark, sf):
    """Actual V streams of each order's parts, packed and unpacked again."""
    udfs.register(spark)
    load(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.collect_list("l_partkey").alias("v")).createOrReplaceTempView("drstore_lists")
    return spark.sql("SELECT l_orderkey, octet_length(b) AS n_bytes, aggregate(vbyte_decode(b), 0L, (a, x) -> a + x) AS total FROM (SELECT l_orderkey, vbyte_encode(v) AS b FROM drstore_lists)")


# -- blocks


@query("block_assignment", f"SELECT doc_id, CAST(floor(start_off / 100000) AS BIGINT) AS block_id FROM ({_PLACES.format(id='doc_id', by='doc_id', text='text', table='documents')})")
def _blocks(spark, sf):
    return inputs.placed(spark, sf, "documents").select("doc_id", baselines.block_number(100_000).alias("block_id"))


@query("block_decode_cost", f"SELECT doc_id, CAST(floor(start_off / 100000) AS BIGINT) AS block_id, start_off - min(start_off) OVER (PARTITION BY floor(start_off / 100000)) + n_bytes AS decoded_bytes FROM ({_PLACES.format(id='doc_id', by='doc_id', text='text', table='documents')})")
def _block_cost(spark, sf):
    return measures.block_cost(inputs.placed(spark, sf, "documents").withColumn("block_id", baselines.block_number(100_000)))


@query("drf_decode_cost", "SELECT CAST(count(*) AS BIGINT) AS n_docs, CAST(sum(octet_length(encode(text))) AS BIGINT) AS decoded_bytes FROM documents")
def _drf_cost(spark, sf):
    """A document of the store costs its own bytes."""
    p = inputs.placed(spark, sf, "documents")
    return factorize.encode(p, inputs.dictionary(p, 1.0), "UV").agg(F.count("*").alias("n_docs"), F.sum("n_bytes").alias("decoded_bytes"))


# -- stores and retrieval


def _written(spark, sf, name: str = "documents", codec: str = "ZV"):
    p = inputs.placed(spark, sf, name)
    d = inputs.dictionary(p)
    path = scratch(spark, "store")
    store.write_store(factorize.encode(p, d, codec), path)
    return p, d, path


@query("requests_sequential", "SELECT r AS req_no, doc_id FROM range(0, (SELECT 3 * count(*) // 2 FROM documents)) AS t(r) JOIN (SELECT doc_id, row_number() OVER (ORDER BY doc_id) - 1 AS place FROM documents) ON place = r % (SELECT count(*) FROM documents)")
def _sequential(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    n = p.count()
    return retrieval.sequential(p, 3 * n // 2, n)


@query("retrieve_sequential", "SELECT r AS req_no, doc_id, md5(text) AS digest FROM range(0, (SELECT count(*) FROM documents)) AS t(r) JOIN (SELECT doc_id, text, row_number() OVER (ORDER BY doc_id) - 1 AS place FROM documents) ON place = r")
def _retrieve_sequential(spark, sf):
    p, d, path = _written(spark, sf)
    n = p.count()
    return store.retrieve(store.read_store(spark, path), d, retrieval.sequential(p, n, n)).select("req_no", "doc_id", F.md5("body").alias("digest"))


_TF = r"tf AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM documents), c AS (SELECT doc_id, term, count(*) AS tf FROM tf GROUP BY ALL)"
_LOG = (
    "WITH " + _TF + r""", df AS (SELECT term, count(*) AS df FROM c GROUP BY 1), dl AS (SELECT doc_id, sum(tf) AS dl FROM c GROUP BY 1), n AS (SELECT count(*) AS n, avg(dl) AS avgdl FROM dl),
q AS (SELECT DISTINCT item_id AS query_no, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM benchmark),
s AS (SELECT query_no, doc_id, round(sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / avgdl))), 6) AS score FROM q JOIN c USING (term) JOIN df USING (term) JOIN dl USING (doc_id), n GROUP BY ALL),
t AS (SELECT *, row_number() OVER (PARTITION BY query_no ORDER BY score DESC, doc_id) AS rank FROM s QUALIFY rank <= 20)
SELECT row_number() OVER (ORDER BY query_no, rank) - 1 AS req_no, query_no, CAST(rank AS INT) AS rank, doc_id FROM t"""
)


def _query_log(spark, sf, cap: int = 100_000) -> DataFrame:
    tf = retrieval.tokens(load(spark, sf, "documents"), "doc_id", F.col("text"))
    q = retrieval.tokens(load(spark, sf, "benchmark"), "item_id", F.col("text")).select(F.col("doc_id").alias("query_no"), "term")
    return retrieval.request_list(retrieval.top_k(retrieval.rank(q, tf)), cap)


@query("requests_query_log", _LOG)
def _requests_log(spark, sf):
    return _query_log(spark, sf)


@query("requests_query_log_cosine")
def _requests_cosine(spark, sf):
    tf = retrieval.tokens(load(spark, sf, "pages"), "page_id", retrieval.strip_html(F.col("html")))
    q = retrieval.tokens(load(spark, sf, "benchmark"), "item_id", F.col("text")).select(F.col("doc_id").alias("query_no"), "term")
    return retrieval.request_list(retrieval.top_k(retrieval.rank(q, tf, "cosine")), 100_000)


@query("retrieve_query_log", f"WITH r AS ({_LOG}) SELECT req_no, doc_id, md5(text) AS digest FROM r JOIN documents USING (doc_id)")
def _retrieve_log(spark, sf):
    _, d, path = _written(spark, sf)
    return store.retrieve(store.read_store(spark, path), d, _query_log(spark, sf)).select("req_no", "doc_id", F.md5("body").alias("digest"))


@query("retrieve_absent_ids", "SELECT r AS req_no, -r - 1 AS doc_id, CAST(NULL AS VARCHAR) AS digest FROM range(0, 5) AS t(r)")
def _absent(spark, sf):
    _, d, path = _written(spark, sf)
    asked = spark.range(5).select(F.col("id").alias("req_no"), (-F.col("id") - 1).alias("doc_id"))
    return store.retrieve(store.read_store(spark, path), d, asked).select("req_no", "doc_id", F.md5("body").alias("digest"))


_ALL_ASKED = "SELECT doc_id AS req_no, doc_id, md5(text) AS digest FROM documents"


@query("retrieve_each_from_blocks", _ALL_ASKED)
def _each_from_blocks(spark, sf):
    """Every request opens its block by itself."""
    p = inputs.placed(spark, sf, "documents")
    asked = p.select(F.col("doc_id").alias("req_no"), "doc_id")
    return baselines.read_blocked_each(baselines.blocked_store(p, "zlib", 100_000), "zlib", asked).select("req_no", "doc_id", F.md5("body").alias("digest"))


@query("retrieve_each", _ALL_ASKED)
def _retrieve_each(spark, sf):
    """Every request is decoded by itself."""
    p, d, path = _written(spark, sf)
    asked = p.select(F.col("doc_id").alias("req_no"), "doc_id")
    return store.retrieve_each(store.read_store(spark, path), d, asked).select("req_no", "doc_id", F.md5("body").alias("digest"))


@query("get_one_by_one", "SELECT doc_id, md5(text) AS digest FROM documents ORDER BY doc_id LIMIT 5")
def _get(spark, sf):
    """Single documents by id; five calls."""
    p, d, path = _written(spark, sf)
    rows = store.read_store(spark, path)
    ids = [r["doc_id"] for r in p.select("doc_id").orderBy("doc_id").limit(5).collect()]
    import hashlib

    return spark.createDataFrame([(i, hashlib.md5(store.get(rows, d, i)).hexdigest()) for i in ids], "doc_id long, digest string")


@query("retrieve_from_blocks", _ALL_ASKED)
def _from_blocks(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    asked = p.select(F.col("doc_id").alias("req_no"), "doc_id")
    return baselines.read_blocked(baselines.blocked_store(p, "zlib", 100_000), "zlib", asked).select("req_no", "doc_id", F.md5("body").alias("digest"))


@query("retrieve_by_offset", _ALL_ASKED)
def _by_offset(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    d = inputs.dictionary(p)
    path = scratch(spark, "segments")
    docmap = store.write_segments(factorize.encode(p, d, "UV"), path)
    asked = p.select(F.col("doc_id").alias("req_no"), "doc_id")
    return store.retrieve_by_offset(path, docmap, asked, d).select("req_no", "doc_id", F.md5("body").alias("digest"))


@query("raw_docmap", f"SELECT doc_id, CAST(doc_id % 8 AS INT) AS segment, CAST(sum(octet_length(encode(text))) OVER (PARTITION BY doc_id % 8 ORDER BY doc_id) - octet_length(encode(text)) AS BIGINT) AS byte_off, CAST(octet_length(encode(text)) AS BIGINT) AS byte_len FROM documents")
def _docmap(spark, sf):
    return store.build_docmap(inputs.documents(spark, sf).select("doc_id", (F.col("doc_id") % 8).cast("int").alias("segment"), F.col("n_bytes").alias("byte_len")))


@query("docmap_audit", "SELECT CAST(NULL AS BIGINT) AS doc_id, CAST(NULL AS VARCHAR) AS fault WHERE false")
def _audit(spark, sf):
    return store.audit_docmap(store.write_segments(inputs.documents(spark, sf), scratch(spark, "segments"), raw=True))


@query("store_audit", "SELECT CAST(NULL AS BIGINT) AS doc_id, CAST(NULL AS VARCHAR) AS digest WHERE false")
def _store_audit(spark, sf):
    """Documents that differ from their stored form, both ways: none."""
    p, d, path = _written(spark, sf)
    back, own = digest(store.decode_all(store.read_store(spark, path), d)), digest(p)
    return own.exceptAll(back).unionByName(back.exceptAll(own))


@query("data_source_scan", "SELECT doc_id, octet_length(encode(text)) AS n_bytes, md5(text) AS digest FROM documents")
def _data_source(spark, sf):
    _, d, path = _written(spark, sf)
    d.save(path + "-dictionary")
    datasource.register(spark)
    rows = spark.read.format("drstore").option("path", path).option("dictionary", path + "-dictionary").load()
    return rows.select("doc_id", "n_bytes", F.md5("body").alias("digest"))


@query("sql_functions", "SELECT doc_id, CAST(octet_length(encode(text)) AS INT) AS n_bytes, md5(text) AS digest FROM documents")
def _sql(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    udfs.register(spark, inputs.dictionary(p, 1.0))
    load(spark, sf, "documents").createOrReplaceTempView("drstore_documents")
    return spark.sql("SELECT doc_id, octet_length(b) AS n_bytes, md5(b) AS digest FROM (SELECT doc_id, drf_decode(drf_factorize(encode(text, 'UTF-8'))) AS b FROM drstore_documents)")


# -- semi-static codes

_SYM = r"sym AS (SELECT unnest(regexp_extract_all(text, '[\p{L}\p{N}]+|[^\p{L}\p{N}]+')) AS symbol FROM documents), fq AS (SELECT symbol, count(*) AS freq FROM sym GROUP BY 1), rk AS (SELECT symbol, freq, row_number() OVER (ORDER BY freq DESC, encode(symbol)) - 1 AS rank FROM fq), ln AS (SELECT *, CASE WHEN rank < 128 THEN 1 WHEN rank < 16512 THEN 2 WHEN rank < 2113664 THEN 3 ELSE 4 END AS len FROM rk)"


def _word_freq(spark, sf):
    return semistatic.frequencies(semistatic.symbols(load(spark, sf, "documents"), "word"))


@query("dense_code_lengths", f"WITH {_SYM} SELECT symbol, freq, rank, CAST(len AS INT) AS len FROM ln")
def _dense_lengths(spark, sf):
    return semistatic.ranked(_word_freq(spark, sf)).withColumn("len", semistatic.dense_length(F.col("rank")))


@query("dense_code_cost", f"WITH {_SYM} SELECT count(*) AS symbols, CAST(sum(freq) AS BIGINT) AS occurrences, CAST(sum(freq * len) AS BIGINT) AS coded_bytes, CAST(sum(octet_length(encode(symbol))) AS BIGINT) AS vocabulary_bytes FROM ln")
def _dense_cost(spark, sf):
    return semistatic.dense_cost(_word_freq(spark, sf))


@query("vocabulary_profile", f"WITH {_SYM} SELECT count(*) AS symbols, count(*) FILTER (freq = 1) AS singletons, count(*) FILTER (freq = 1 AND NOT regexp_matches(symbol, '^[\\p{{L}}\\p{{N}}]')) AS singleton_non_words, CAST(sum(octet_length(encode(symbol))) AS BIGINT) AS vocabulary_bytes, CAST(sum(freq) AS BIGINT) AS occurrences FROM fq")
def _profile(spark, sf):
    return semistatic.vocabulary_profile(semistatic.symbols(load(spark, sf, "documents"), "word"))


@query(
    "w17_vocabulary_growth",
    f"WITH p AS (SELECT text, start_off, CAST(10 * start_off // sum(n_bytes) OVER () AS BIGINT) AS tenth FROM (SELECT *, octet_length(encode(text)) AS n_bytes, sum(octet_length(encode(text))) OVER (ORDER BY doc_id) - octet_length(encode(text)) AS start_off FROM documents)), "
    + r"sym AS (SELECT tenth, unnest(regexp_extract_all(text, '[\p{L}\p{N}]+|[^\p{L}\p{N}]+')) AS symbol FROM p), fst AS (SELECT symbol, min(tenth) AS tenth FROM sym GROUP BY 1), n AS (SELECT tenth, count(*) AS fresh FROM fst GROUP BY 1), o AS (SELECT tenth, count(*) AS seen FROM sym GROUP BY 1) "
    + "SELECT tenth, CAST(sum(coalesce(fresh, 0)) OVER (ORDER BY tenth) AS BIGINT) AS symbols, CAST(sum(seen) OVER (ORDER BY tenth) AS BIGINT) AS occurrences FROM o LEFT JOIN n USING (tenth)",
)
def _growth(spark, sf):
    """Distinct symbols of the first tenth of the collection, of the first two, and so on: a symbol counts from the tenth where it comes first."""
    p = inputs.placed(spark, sf, "documents")
    n = max(col.total_bytes(p), 1)
    tenths = p.select("doc_id", F.floor(10 * F.col("start_off").cast("decimal(38,0)") / n).cast("long").alias("tenth"), F.decode("body", "UTF-8").alias("text"))
    words = F.expr(r"regexp_extract_all(text, '[\\p{L}\\p{N}]+|[^\\p{L}\\p{N}]+', 0)")
    by = tenths.select("tenth", F.explode(words).alias("symbol")).groupBy("symbol", "tenth").agg(F.count("*").alias("n"))
    fresh = by.groupBy("symbol").agg(F.min("tenth").alias("tenth")).groupBy("tenth").agg(F.count("*").alias("fresh"))
    rows = by.groupBy("tenth").agg(F.sum("n").alias("seen")).join(fresh, "tenth", "left")
    w = Window.orderBy("tenth")  # ten rows
    return rows.select("tenth", F.sum(F.coalesce("fresh", F.lit(0))).over(w).cast("long").alias("symbols"), F.sum("seen").over(w).cast("long").alias("occurrences"))


@query("character_frequencies", "SELECT symbol, count(*) AS freq FROM (SELECT unnest(string_split(text, '')) AS symbol FROM documents) WHERE symbol <> '' GROUP BY 1")
def _char_freq(spark, sf):
    return semistatic.frequencies(semistatic.symbols(load(spark, sf, "documents"), "char"))


def _costs(spark, sf, freqs: list[tuple[str, DataFrame]], raw: int) -> DataFrame:
    out = None
    for name, f, arity, bits in freqs:
        part = semistatic.huffman_cost(f, arity, bits).select(F.lit(name).alias("code"), "symbols", "occurrences", F.ceil(F.col("coded_bits") / 8).alias("coded_bytes"))
        part = part.withColumn("pct", F.round(100.0 * F.col("coded_bytes") / raw, 4))
        out = part if out is None else out.unionByName(part)
    return out


def _huffman_sql(symbols: str, code: str, arity: int, bits: int) -> str:
    """The least weights are merged again and again; a code's length in digits is the sum of all merged weights."""
    return f"""SELECT '{code}' AS code, (SELECT count(*) FROM {symbols}) AS symbols, (SELECT CAST(sum(freq) AS BIGINT) FROM {symbols}) AS occurrences, CAST(max(total) * {bits} AS BIGINT) AS coded_bits FROM (
WITH RECURSIVE m AS (
  SELECT list_sort(list(freq)) AS l, 2 + (count(*) - 2) % ({arity} - 1) AS k, CAST(0 AS BIGINT) AS total FROM {symbols}
  UNION ALL
  SELECT list_sort(list_append(l[k + 1:], CAST(list_sum(l[:k]) AS BIGINT))), {arity}, total + CAST(list_sum(l[:k]) AS BIGINT) FROM m WHERE len(l) > 1
) SELECT total FROM m)"""


_CHARS = "ch AS (SELECT symbol, count(*) AS freq FROM (SELECT unnest(string_split(text, '')) AS symbol FROM documents) WHERE symbol <> '' GROUP BY 1)"


@query("huffman_costs", f"WITH {_SYM}, {_CHARS}, c AS ({_huffman_sql('ch', 'char bit', 2, 1)} UNION ALL {_huffman_sql('fq', 'word byte', 256, 8)} UNION ALL {_huffman_sql('fq', 'word tagged', 128, 8)}) SELECT code, symbols, occurrences, CAST((coded_bits + 7) // 8 AS BIGINT) AS coded_bytes, round(100.0 * ((coded_bits + 7) // 8) / {_N}, 4) AS pct FROM c")
def _huffman(spark, sf):
    """Characters in bits, words in plain (256) and tagged (128) bytes."""
    raw = col.total_bytes(inputs.documents(spark, sf))
    words = _word_freq(spark, sf)
    chars = semistatic.frequencies(semistatic.symbols(load(spark, sf, "documents"), "char"))
    return _costs(spark, sf, [("char bit", chars, 2, 1), ("word byte", words, 256, 8), ("word tagged", words, 128, 8)], raw)


@query("huffman_word_bits")
def _huffman_words(spark, sf):
    """Words in bits; merging them two by two is too long for SQL."""
    return _costs(spark, sf, [("word bit", _word_freq(spark, sf), 2, 1)], col.total_bytes(inputs.documents(spark, sf)))


@query("dense_pair_and_phrase_costs")
def _pairs(spark, sf):
    """Phrases are pairs of words and pairs."""
    counted = lambda lists: cut(semistatic.frequencies(semistatic.listed(lists)))
    words = semistatic.symbol_lists(load(spark, sf, "documents"), "word")
    word_freq = counted(words)
    pairs = semistatic.pair_lists(words, 2000, word_freq)
    pair_freq = counted(pairs)
    phrase_freq = counted(semistatic.pair_lists(pairs, 2000, pair_freq))
    out = None
    for name, freq in (("words", word_freq), ("pairs", pair_freq), ("phrases", phrase_freq)):
        part = semistatic.dense_cost(freq).select(F.lit(name).alias("code"), "*")
        out = part if out is None else out.unionByName(part)
    return out


@query("pair_symbols_roundtrip", DOC_DIGEST + " WHERE text <> ''")
def _pairs_roundtrip(spark, sf):
    s = semistatic.pair_lists(semistatic.symbol_lists(load(spark, sf, "documents"), "word"), 500)
    return s.where(F.size("symbols") > 0).select("doc_id", F.md5(F.array_join("symbols", "")).alias("digest"))


# -- slices


@query("bytes_by_lang_and_source", "SELECT lang, source, CAST(sum(octet_length(encode(text))) AS BIGINT) AS raw_bytes, count(*) AS n_docs, CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS level FROM documents GROUP BY ROLLUP (lang, source)")
def _slices(spark, sf):
    d = load(spark, sf, "documents")
    return d.rollup("lang", "source").agg(F.sum(F.octet_length("text")).alias("raw_bytes"), F.count("*").alias("n_docs"), F.grouping_id().alias("level"))


@query("uv_floor_by_label", "SELECT quality, toxic, count(*) AS n_docs, CAST(sum(octet_length(encode(text))) AS BIGINT) AS raw_bytes FROM documents JOIN labels USING (doc_id) GROUP BY CUBE (quality, toxic)")
def _labels(spark, sf):
    rows = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id")
    return rows.cube("quality", "toxic").agg(F.count("*").alias("n_docs"), F.sum(F.octet_length("text")).alias("raw_bytes"))


@query("bytes_by_host", "SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host, count(*) AS n_docs, CAST(sum(octet_length(encode(html))) AS BIGINT) AS raw_bytes FROM pages GROUP BY 1")
def _hosts(spark, sf):
    return load(spark, sf, "pages").groupBy(F.expr("parse_url(url, 'HOST')").alias("host")).agg(F.count("*").alias("n_docs"), F.sum(F.octet_length("html")).alias("raw_bytes"))


@query("distance_of_copies", f"SELECT a.digest, count(*) AS copies, CAST(max(start_off) - min(start_off) AS BIGINT) AS span FROM (SELECT md5(text) AS digest, sum(octet_length(encode(text))) OVER (ORDER BY doc_id) - octet_length(encode(text)) AS start_off FROM documents) a GROUP BY 1 HAVING count(*) > 1")
def _copies(spark, sf):
    return inputs.placed(spark, sf, "documents").groupBy(F.md5("body").alias("digest")).agg(F.count("*").alias("copies"), (F.max("start_off") - F.min("start_off")).alias("span")).where("copies > 1")
