"""The store on Spark: places, samples, partition invariance, plans, retrieval and streams."""

import lzma
import zlib

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from drstore import schemas
from drstore.operators import baselines, codecs
from drstore.operators import collection as col
from drstore.operators import dictionary as dic
from drstore.operators import factorize, measures
from drstore.operators.suffix import Searcher
from drstore.plans import inputs, workloads
from drstore.sources import store
from drstore.sources.tables import TABLES, load

QUICK = ("collection_offsets", "prefix_cut", "even_sample_positions", "even_sample_bytes", "worked_example_factors", "worked_example_trace", "suffix_array_distributed", "factor_positions_benchmark", "unused_pct_benchmark", "avg_factor_len_benchmark", "position_skew_benchmark", "host_order_documents", "huffman_costs", "retrieve_each", "retrieve_each_from_blocks", "get_one_by_one", "roundtrip_ZZ_pages", "roundtrip_zlib_100k", "requests_query_log", "retrieve_by_offset", "data_source_scan", "dense_code_cost", "request_sessions", "version_in_force", "stream_request_windows", "join_ranges_by_stripe", "set_operations")


def _same(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    q, o = __spark_entry__.queries()[name], __spark_entry__.oracle_sql()[name]
    got = q(spark, sf).toPandas()
    want = con.execute(o).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert _rows(got) == _rows(want)


def _rows(df):
    def plain(v):
        if v is None or (not isinstance(v, (list, np.ndarray)) and pd.isna(v)):
            return ""
        return f"{float(v):.9g}" if isinstance(v, (int, float, np.integer, np.floating)) and not isinstance(v, bool) else str(v)

    return sorted(tuple(map(plain, r)) for r in df[sorted(df.columns)].astype(object).values.tolist())


@pytest.mark.parametrize("name", QUICK)
def test_against_sql(spark, sf, name):
    _same(spark, sf, name)


def test_entry(spark):
    r = __spark_entry__.entry(spark).first()
    assert r["ok"] and r["n_docs"] > 0


@pytest.mark.parametrize("parts", [1, 3, 7])
def test_places_and_codes_do_not_depend_on_partitions(spark, sf, parts):
    coll = inputs.pages(spark, sf).repartition(parts)
    p = col.with_offsets(coll)
    d = dic.build(p, dic.DictSpec(pct=4.0, s=512))
    whole = b"".join(bytes(r["body"]) for r in p.orderBy("ord").collect())
    n, c = len(whole), int(len(whole) * 0.04) // 512
    assert d.data == b"".join(whole[k * n // c : k * n // c + 512] for k in range(c))
    size = factorize.encode(p, d, "UV").agg(F.sum(F.octet_length("pos_stream")), F.sum(F.octet_length("len_stream"))).first()
    f = factorize.factorize(p, d)
    k = measures.lengths(f).agg(F.count("*").alias("n"), F.sum(measures.vbyte_size(F.col("len"))).alias("v")).first()
    assert (size[0], size[1]) == (4 * k["n"], k["v"])
    schemas.require(p, schemas.COLLECTION.replace("ord long, ", ""))


def test_edges_of_dictionaries(spark):
    rows = spark.createDataFrame([(1, "abc"), (2, None), (3, ""), (4, "äöü€" * 5)], "doc_id long, text string")
    p = col.with_offsets(col.as_collection(rows, "doc_id", "text"))
    n = col.total_bytes(p)
    assert dic.build(p, dic.DictSpec(m_bytes=10 * n, s=4)).data == b"".join(bytes(r["body"]) for r in p.orderBy("ord").collect())
    with pytest.raises(ValueError):
        dic.even_samples(p, 3, 10)
    for kind in ("even", "documents", "head"):
        d = dic.build(p, dic.DictSpec(m_bytes=12, s=4, kind=kind))
        back = {r["doc_id"]: bytes(r["body"]).decode() for r in factorize.decode_encoded(factorize.encode(p, d, "ZV"), d).collect()}
        assert back == {1: "abc", 2: "", 3: "", 4: "äöü€" * 5}
    empty = col.with_offsets(col.as_collection(rows.limit(0), "doc_id", "text"))
    assert empty.count() == 0


def test_requests_keep_order_and_duplicates(spark, sf, tmp_path):
    p = inputs.placed(spark, sf, "documents")
    d = inputs.dictionary(p, 1.0)
    store.write_store(factorize.encode(p, d, "UV"), str(tmp_path / "s"))
    s = store.read_store(spark, str(tmp_path / "s"))
    ids = [5, 3, 5, -7, 3]
    asked = spark.createDataFrame(list(enumerate(ids)), schemas.REQUESTS)
    got = store.retrieve(s, d, asked).orderBy("req_no").collect()
    assert [r["doc_id"] for r in got] == ids and [r["body"] is None for r in got] == [False, False, False, True, False]
    assert store.get(s, d, 5).decode() == spark.read.parquet(f"{sf}/documents.parquet").where("doc_id = 5").first()["text"]
    plan = s.where("doc_id = 5").select("doc_id", "len_stream")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(doc_id), EqualTo(doc_id,5)]" in plan and "pos_stream" not in plan


def test_plans_have_no_products_and_factoring_no_shuffle(spark, sf):
    p = inputs.documents(spark, sf)
    d = dic.Dictionary(b"the of and to in is that")
    plan = factorize.encode(p, d, "ZV")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "ReadSchema: struct<doc_id:bigint,text:string>" in plan


def test_appends_extend_and_restart(spark, tmp_path):
    from drstore.streaming.append import Appender, Monitor

    d = dic.Dictionary(b"plain words only ")
    a = Appender(spark, str(tmp_path / "a"), d, s=16, m_extra=64, monitor=Monitor(tau=1.0, weight=1.0))
    rows = lambda k, t: spark.createDataFrame([(k * 10 + i, t * 5) for i in range(4)], "doc_id long, text string")
    a.write_batch(rows(0, "plain words only "), 0)
    a.write_batch(rows(1, "other content 123 "), 1)
    a.write_batch(rows(1, "other content 123 "), 1)  # a batch that is run again replaces itself
    a.write_batch(rows(2, "other content 123 "), 2)
    assert [x["batch"] for x in a.log] == [0, 1, 2] and a.dictionary.version >= 1
    back = {r["doc_id"]: bytes(r["body"]).decode() for r in factorize.decode_encoded(a.store(), a.dictionary).collect()}
    assert len(back) == 12 and back[0] == "plain words only " * 5 and back[21] == "other content 123 " * 5


def test_bucketed_stores_join_without_an_exchange(spark, sf):
    p = inputs.pages(spark, sf)
    d = dic.Dictionary(b"<html><body><p></p></body></html>")
    store.write_bucketed(factorize.encode(p, d, "UV"), "drstore_bucketed", 4)
    store.write_bucketed(p.select("doc_id", F.col("n_bytes").alias("size")), "drstore_sizes", 4)
    held = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        j = spark.table("drstore_bucketed").join(spark.table("drstore_sizes"), "doc_id")
        assert "Exchange" not in j._jdf.queryExecution().executedPlan().toString()
        assert j.where("size <> n_bytes").count() == 0 and j.count() == p.count()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", held)
        spark.sql("DROP TABLE drstore_bucketed")
        spark.sql("DROP TABLE drstore_sizes")


@pytest.mark.parametrize("name", ["retrieve_from_blocks", "window_lz_roundtrip", "pair_grammar_roundtrip", "end_aligned_lz_roundtrip", "dynamic_dense_roundtrip", "decode_builtin", "stream_stream_join", "stream_ratio_drift", "roundtrip_codec_grid"])
def test_whole_tables_against_sql(spark, sf, name):
    _same(spark, sf, name)


def test_factors_of_all_documents(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    d, bodies = inputs.dictionary(p).data, {r["doc_id"]: bytes(r["body"]) for r in p.collect()}
    at = dict.fromkeys(bodies, 0)
    for r in __spark_entry__.queries()["factor_lengths"](spark, sf).orderBy("doc_id", "seq").collect():
        x, i, k = bodies[r["doc_id"]], r["doc_off"], r["len"]
        assert i == at[r["doc_id"]] and (k == 0 or x[i : i + k] in d)
        assert i + k == len(x) or x[i : i + k + 1] not in d
        at[r["doc_id"]] += max(k, 1)
    assert at == {k: len(x) for k, x in bodies.items()}


def test_places_keep_null_and_repeated_ids(spark):
    rows = spark.createDataFrame([(3, "ccc"), (None, "n"), (3, "cc"), (1, "a"), (None, None), (3, "ccc")], "doc_id long, text string").repartition(3)
    got = [tuple(r) for r in col.with_offsets(col.as_collection(rows, "doc_id", "text")).select("doc_id", F.decode("body", "UTF-8"), "ord", "start_off").orderBy("ord").collect()]
    assert [r[2] for r in got] == list(range(6)) and [r[0] for r in got] == [None, None, 1, 3, 3, 3]
    assert sorted(r[1] for r in got) == ["", "a", "cc", "ccc", "ccc", "n"]
    at = 0
    for _, body, _, start in got:
        assert start == at
        at += len(body)


def test_documents_are_encoded_once_on_write(spark, sf, tmp_path):
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    p = inputs.placed(spark, sf, "documents")
    enc = factorize.encode(p.select("doc_id", "body").mapInArrow(count, "doc_id long, body binary"), dic.Dictionary(b"the of and to"), "UV")
    store.write_store(enc, str(tmp_path / "s"))
    assert seen.value == p.count() == store.read_store(spark, str(tmp_path / "s")).count()


def test_hot_requests_are_dealt_to_several_tasks(spark):
    bodies = spark.createDataFrame([(i, f"b{i}") for i in range(3)], "doc_id long, body string")
    asked = spark.range(700).select(F.col("id").alias("req_no"), F.when(F.col("id") < 600, 1).otherwise(F.col("id") % 4).cast("long").alias("doc_id"))
    store.HOT_REQUESTS, held = 50, store.HOT_REQUESTS
    try:
        got = {r["req_no"]: (r["doc_id"], r["body"]) for r in store.delivered(asked, bodies, "body").collect()}
    finally:
        store.HOT_REQUESTS = held
    assert got == {i: (k, f"b{k}" if k < 3 else None) for i, k in ((i, 1 if i < 600 else i % 4) for i in range(700))}


def test_mapped_dictionaries_work_as_sent_ones(spark, sf, monkeypatch):
    p = inputs.documents(spark, sf)
    d = dic.build(inputs.placed(spark, sf, "documents"), dic.DictSpec(pct=4.0, s=512))
    rows = lambda: {r["doc_id"]: (bytes(r["pos_stream"]), bytes(r["len_stream"])) for r in factorize.encode(p, d, "UV").collect()}
    want = rows()
    monkeypatch.setattr(dic, "BROADCAST_BYTES", 100)
    assert rows() == want
    assert factorize.decode_encoded(factorize.encode(p, d, "UV"), d).join(p.withColumnRenamed("body", "own"), "doc_id").where("body <> own").count() == 0


def test_a_rebuild_replaces_what_is_stored(spark, tmp_path):
    from drstore.streaming.append import Appender

    a = Appender(spark, str(tmp_path / "r"), dic.Dictionary(b"plain words only "), s=16)
    rows = lambda k, t: spark.createDataFrame([(k * 10 + i, t * 5) for i in range(4)], "doc_id long, text string")
    a.write_batch(rows(0, "plain words only "), 0)
    a.write_batch(rows(1, "other content 123 "), 1)
    whole = col.as_collection(rows(0, "plain words only ").unionByName(rows(1, "other content 123 ")), "doc_id", "text")
    a.rebuild(whole, dic.DictSpec(m_bytes=64, s=16))
    a.write_batch(rows(2, "other content 123 "), 2)
    back = {r["doc_id"]: bytes(r["body"]).decode() for r in factorize.decode_encoded(a.store(), a.dictionary).collect()}
    assert a.dictionary.epoch == 1 and len(back) == 12 and back[0] == "plain words only " * 5 and back[21] == "other content 123 " * 5


def test_windows_reach_over_all_documents(spark, sf):
    ends = [(r["doc_id"], r["start_off"], r["start_off"] + r["n_bytes"]) for r in inputs.placed(spark, sf, "documents").collect()]
    windows = range(-(-max(e for *_, e in ends) // 25000))
    want = {(k, i) for k in windows for i, a, e in ends if a < k * 25000 + 700 and e > k * 25000 and e > a}
    assert {tuple(r) for r in __spark_entry__.queries()["join_ranges_by_stripe"](spark, sf).collect()} == want


def test_experiments_have_their_whole_grids(spark, sf):
    q = __spark_entry__.queries()
    prefixes = {r["prefix_pct"] for r in q["w11_prefix_dictionaries"](spark, sf).select("prefix_pct").collect()}
    assert prefixes == {100.0, 90.0, 80.0, 70.0, 60.0, 50.0, 40.0, 30.0, 20.0, 10.0, 1.0}
    n = col.total_bytes(inputs.placed(spark, sf, "documents"))
    room = {(pct, s) for pct in inputs.WIDE for s in inputs.SAMPLES if int(n * pct / 100) >= 2 * s}
    got = q["w03_factor_grid_documents"](spark, sf).select("pct", "s").collect()
    assert {tuple(r) for r in got} == room and {s for _, s in room} == set(inputs.SAMPLES)
    log = q["w13_query_log_with_user_turns"](spark, sf)
    assert log.where(f"query_no >= {1 << 32}").count() > 0 and log.where(f"query_no < {1 << 32}").count() > 0


def test_of_events_with_the_least_value_the_least_id_counts(spark, tmp_path):
    rows = spark.createDataFrame([(5, "a", 1.0), (3, "a", 1.0), (9, "a", 1.0), (1, "a", 2.0), (None, "a", 0.5), (2, "a", None), (4, "b", 60.0)], "event_id long, event_type string, value double")
    rows.coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    got = __spark_entry__.queries()["aggregate_statistics"](spark, str(tmp_path)).collect()
    assert {r["event_type"]: r["least"] for r in got} == {"a": 3, "b": 4}


@pytest.mark.parametrize("name", ["worked_example_suffixes", "worked_example_trace", "worked_example_factors"])
def test_worked_examples_are_of_given_tables(spark, sf, name):
    rows = __spark_entry__.queries()[name](spark, sf)
    texts = {r["doc_id"]: bytes(r["body"]) for r in inputs.benchmark(spark, sf).where("n_bytes > 0").collect()}
    if name == "worked_example_suffixes":
        assert rows.count() == len(inputs.little_dictionary(spark, sf).data)
    else:
        assert {r["doc_id"] for r in rows.select("doc_id").collect()} == set(texts)
    _same(spark, sf, name)


def test_table_functions_give_the_worked_example(spark):
    from drstore.functions import udfs

    for name, f in udfs.for_dictionary(spark, dic.Dictionary(b"cabbaabba")).items():
        if name in ("drf_factors", "refine_trace"):
            spark.udtf.register(name, f)
    x = b"bbaancabb".hex()
    assert [tuple(r) for r in spark.sql(f"SELECT * FROM drf_factors(X'{x}') ORDER BY seq").collect()] == [(0, 2, 4), (1, 110, 0), (2, 0, 4)]
    assert [tuple(r) for r in spark.sql(f"SELECT * FROM refine_trace(X'{x}') ORDER BY j").collect()] == [(0, 4, 7), (1, 6, 7), (2, 6, 7), (3, 7, 7), (4, None, None)]


def test_pairs_are_joined_left_to_right_inside_each_row(spark):
    from drstore.operators import semistatic

    lists = spark.createDataFrame([(1, ["a", "a", "a", "b"] * 3), (1, ["a", "b"] * 4), (2, []), (3, ["b"]), (None, None)], "doc_id long, symbols array<string>")
    got = sorted(((r["doc_id"] or 0, r["symbols"] or []) for r in semistatic.pair_lists(lists, 1).collect()), key=str)
    assert got == sorted([(1, ["a", "a", "ab"] * 3), (1, ["ab"] * 4), (2, []), (3, ["b"]), (0, [])], key=str)
    plan = semistatic.phrase_lists(lists, 2)._jdf.queryExecution().optimizedPlan().toString()
    assert "Window" not in plan and "Join" not in plan


def _squeezed(bodies: list[bytes], d: dic.Dictionary, codec: str) -> float:
    """Size in % with map and dictionary, a document and a stream at a time."""
    size = 0
    for x in bodies:
        pos, length = factorize.factor_document(x, Searcher(d.data, d.sa))
        size += sum(map(len, codecs.encode_pairs(np.array(pos, np.int64), np.array(length, np.int64), codec)))
    return 100.0 * (size + 24 * len(bodies) + len(d.data)) / sum(map(len, bodies))


def test_url_effect_places_pages_once_an_order(spark, sf, monkeypatch):
    calls, with_offsets = [], col.with_offsets
    monkeypatch.setattr(col, "with_offsets", lambda *a, **b: calls.append(1) or with_offsets(*a, **b))
    got = {r["store"]: r for r in workloads._url_effect(spark, sf).collect()}
    assert len(calls) == 2
    rows = load(spark, sf, "pages").orderBy("page_id").collect()
    for order, by in (("natural", lambda r: r["page_id"]), ("url", lambda r: (r["url"], r["page_id"]))):
        bodies = [r["html"].encode() for r in sorted(rows, key=by)]
        whole, off = b"".join(bodies), np.cumsum([0, *map(len, bodies)])
        for pct in inputs.WIDE:
            c = int(len(whole) * pct / 100) // 512
            d = dic.Dictionary(b"".join(whole[k * len(whole) // c : k * len(whole) // c + 512] for k in range(c)))
            for codec in codecs.PAIR_CODECS:
                assert got[f"dictionary {codec} {pct}"][order] == pytest.approx(_squeezed(bodies, d, codec))
        for size in baselines.BLOCK_SIZES:
            blocks = {}
            for i, (x, o) in enumerate(zip(bodies, off, strict=False)):
                blocks.setdefault(o // size if size else i, []).append(x)
            for name, squeeze in (("zlib", lambda b: zlib.compress(b, 9)), ("lzma", lzma.compress)):
                want = 100.0 * sum(len(squeeze(b"".join(b))) for b in blocks.values()) / len(whole)
                assert got[f"{name} {size}"][order] == pytest.approx(want)
    assert len(got) == 4 * 4 + 2 * 5 + 1 and got["raw 0"]["gain"] == 0


def test_codec_grid_counts_each_row_once(spark, sf, monkeypatch):
    pages = load(spark, sf, "pages")
    odd = pages.unionByName(pages.limit(3)).unionByName(pages.limit(2).withColumn("page_id", F.lit(None).cast("long")))
    monkeypatch.setattr(inputs, "pages", lambda s, d, *keep: col.as_collection(odd, "page_id", "html", keep))
    n = odd.agg(F.sum(F.octet_length(F.encode("html", "UTF-8")))).first()[0]
    rows = workloads.codec_grid(spark, sf, "pages", sizes=(4.0,)).collect()
    assert [(r["n_docs"], r["raw_bytes"]) for r in rows] == [(odd.count(), n)] * 4


def test_codecs_of_no_documents_have_rows(spark, sf, monkeypatch):
    none = load(spark, sf, "pages").limit(0)
    monkeypatch.setattr(inputs, "pages", lambda s, d, *keep: col.as_collection(none, "page_id", "html", keep))
    rows = workloads.codec_grid(spark, sf, "pages", sizes=(4.0,)).collect()
    assert sorted((r["codec"], r["n_docs"], r["enc_pct"]) for r in rows) == [(c, 0, None) for c in sorted(codecs.PAIR_CODECS)]


@pytest.mark.parametrize("names", [("ZZ", "ZV", "UZ", "UV"), ("Zi", "SP", "ZZ")])
def test_streams_that_codecs_share_are_the_same(spark, sf, names):
    p = inputs.placed(spark, sf, "pages")
    f = factorize.factorize(p, inputs.dictionary(p), carry=("n_bytes",)).cache()
    key = lambda r: (r["codec"], r["doc_id"])
    together = sorted(factorize.recode(f, names, carry=("n_bytes",)).collect(), key=key)
    alone = sorted((r for c in names for r in factorize.recode(f, c, carry=("n_bytes",)).collect()), key=key)
    assert together == alone and len(together) == len(names) * p.count()
