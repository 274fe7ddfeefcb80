"""The paper's experiments on the given tables. Each returns rows (config columns ..., measures) and is registered as a query without SQL. Speeds are seconds of whole runs on the machine at hand.

pages stand in for the web crawl, documents for the encyclopedia. Dictionary sizes go by ratio: the published classes (S, M, L) and the wide set 1, 2, 4, 8 %, never
mixed in one table. Grids leave out sizes that have no room for two samples.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, factorize, measures, retrieval
from ..operators import collection as col
from ..operators import dictionary as dic
from ..operators.codecs import PAIR_CODECS
from ..sources import store
from ..sources.tables import load
from . import inputs
from .queries import _query_log, query, scratch

#: the eleven prefixes, in % of the collection
PREFIXES = (100.0, 90.0, 80.0, 70.0, 60.0, 50.0, 40.0, 30.0, 20.0, 10.0, 1.0)


def _table(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


#: Grids that are made at once, each with a dictionary on the driver at most.
AT_ONCE = 3


def _side_by_side(spark: SparkSession, makers: list[Callable[[], DataFrame]]) -> list[DataFrame]:
    """Small tables - a row a store - that are planned and run ``AT_ONCE`` at a time."""

    def rows(make: Callable[[], DataFrame]) -> DataFrame:
        t = make()
        return spark.createDataFrame(t.collect(), t.schema)

    with ThreadPoolExecutor(AT_ONCE) as pool:
        return [x.result() for x in [pool.submit(inheritable_thread_target(spark)(rows), m) for m in makers]]


def factor_grid(spark: SparkSession, sf: str, name: str, sizes=inputs.WIDE, samples=inputs.SAMPLES) -> DataFrame:
    """Mean factor length and unused share for dictionary sizes x sample sizes."""
    p = inputs.placed(spark, sf, name).cache()
    n, parts = col.total_bytes(p), []
    for pct in sizes:
        for s in samples:
            if int(n * pct / 100) < 2 * s:
                continue
            d = dic.build(p, dic.DictSpec(pct=pct, s=s))
            f = factorize.factorize(p, d)
            row = measures.length_stats(f, s).crossJoin(measures.unused_pct(f, len(d.data)))
            parts.append(row.select(F.lit(name).alias("collection"), F.lit(pct).alias("pct"), F.lit(s).alias("s"), "m", "n_factors", "avg_factor_len", "avg_match_len", "literal_share", "under_100", "up_to_sample", "one_byte", "unused_pct"))
    if not parts:  # a collection too small for any of the sizes
        return spark.createDataFrame([], "collection string, pct double, s int, m long, n_factors long, avg_factor_len double, avg_match_len double, literal_share double, under_100 double, up_to_sample double, one_byte double, unused_pct double")
    return _table(parts)


query("w02_factor_grid_pages")(lambda spark, sf: factor_grid(spark, sf, "pages"))
query("w03_factor_grid_documents")(lambda spark, sf: factor_grid(spark, sf, "documents"))
query("w02_factor_grid_pages_published_classes")(lambda spark, sf: factor_grid(spark, sf, "pages", inputs.CLASSES["pages"].values()))
query("w03_factor_grid_documents_published_classes")(lambda spark, sf: factor_grid(spark, sf, "documents", inputs.CLASSES["documents"].values()))


@query("w04_length_histogram")
def _w04(spark, sf):
    parts = []
    for name in ("pages", "documents"):
        p = inputs.placed(spark, sf, name)
        n = col.total_bytes(p)
        for s in inputs.SAMPLES:
            if int(n * 4.0 / 100) < 2 * s:
                continue
            d = dic.build(p, dic.DictSpec(pct=4.0, s=s))
            parts.append(measures.histogram(factorize.factorize(p, d)).select(F.lit(name).alias("collection"), F.lit(s).alias("s"), "bin", "cnt"))
    return _table(parts)


def codec_rows(p: DataFrame, name: str, order: str, pct: float, codecs=PAIR_CODECS) -> DataFrame:
    """Encoded size for a dictionary size x pair codecs: factors are found once, streams that codecs share are coded once."""
    d = dic.build(p, dic.DictSpec(pct=pct, s=512))
    f = factorize.factorize(p, d, carry=("n_bytes",))
    size = measures.ratio(factorize.recode(f, codecs, carry=("n_bytes",)), len(d.data), codecs=codecs)
    return size.select(F.lit(name).alias("collection"), F.lit(order).alias("doc_order"), F.lit(pct).alias("pct"), "codec", "n_docs", "raw_bytes", "enc_bytes", "enc_pct", "enc_pct_with_map", "enc_pct_total")


def codec_grid(spark: SparkSession, sf: str, name: str, order: str = "natural", sizes=inputs.WIDE, codecs=PAIR_CODECS) -> DataFrame:
    """Encoded size for dictionary sizes x pair codecs."""
    p = inputs.placed(spark, sf, name, order).cache()
    return _table([codec_rows(p, name, order, pct, codecs) for pct in sizes])


query("w05_codecs_pages")(lambda spark, sf: codec_grid(spark, sf, "pages"))
query("w06_codecs_pages_url_order")(lambda spark, sf: codec_grid(spark, sf, "pages", "url"))
query("w09_codecs_documents")(lambda spark, sf: codec_grid(spark, sf, "documents"))


@query("w05_codecs_pages_published_classes")
def _classes(spark, sf, name: str = "pages", order: str = "natural"):
    """The published ratio classes; samples are shortened to what the dictionary has room for."""
    p = inputs.placed(spark, sf, name, order)
    n, parts = col.total_bytes(p), []
    for label, pct in inputs.CLASSES[name].items():
        m = int(n * pct / 100)
        d = dic.build(p, dic.DictSpec(m_bytes=m, s=max(64, min(512, m // 4))))
        f = factorize.factorize(p, d).cache()
        for c in PAIR_CODECS:
            enc = factorize.recode(f, c).join(p.select("doc_id", "n_bytes"), "doc_id")
            parts.append(measures.ratio(enc, len(d.data)).select(F.lit(label).alias("class"), F.lit(c).alias("codec"), "enc_pct", "enc_pct_total"))
    return _table(parts)


query("w06_codecs_pages_url_order_published_classes")(lambda spark, sf: _classes(spark, sf, "pages", "url"))
query("w09_codecs_documents_published_classes")(lambda spark, sf: _classes(spark, sf, "documents"))


def block_rows(p: DataFrame, codecs=("zlib", "lzma"), sizes=baselines.BLOCK_SIZES) -> DataFrame:
    """Size of blocked stores of a placed collection, and the mean bytes that one request decodes."""
    parts = [p.agg(F.sum("n_bytes").alias("raw_bytes")).select(F.lit("raw").alias("codec"), F.lit(0).alias("block"), F.lit(100.0).alias("enc_pct"), F.lit(0.0).alias("decoded_per_request"))]
    for size in sizes:
        cost = measures.block_cost(p.withColumn("block_id", baselines.block_number(size))).agg(F.avg("decoded_bytes").alias("decoded_per_request"))
        parts.append(baselines.blocked_ratio(baselines.blocked_store(p, codecs, size), codecs).crossJoin(cost).select("codec", F.lit(size).alias("block"), "enc_pct", "decoded_per_request"))
    return _table(parts)


def block_grid(spark: SparkSession, sf: str, name: str, order: str = "natural", codecs=("zlib", "lzma"), sizes=baselines.BLOCK_SIZES) -> DataFrame:
    """The same of a table in an order."""
    return block_rows(inputs.placed(spark, sf, name, order).cache(), codecs, sizes)


query("w07_blocks_pages")(lambda spark, sf: block_grid(spark, sf, "pages"))
query("w08_blocks_pages_url_order")(lambda spark, sf: block_grid(spark, sf, "pages", "url"))
query("w10_blocks_documents")(lambda spark, sf: block_grid(spark, sf, "documents"))
query("w18_large_window")(lambda spark, sf: block_grid(spark, sf, "documents", codecs=("lzma-128",), sizes=(1_000_000, 128_000_000)))


@query("w11_prefix_dictionaries")
def _w11(spark, sf, prefixes=PREFIXES):
    """Dictionaries of one size sampled from prefixes; loss against the whole."""
    p, parts = inputs.placed(spark, sf, "documents"), []
    for q in prefixes:
        d = dic.from_prefix(p, q, dic.DictSpec(pct=1.0, s=512))
        parts.append(measures.ratio(factorize.encode(p, d, "ZZ"), len(d.data)).select(F.lit(q).alias("prefix_pct"), "enc_pct"))
    t = _table(parts)
    whole = t.where("prefix_pct = 100").select(F.col("enc_pct").alias("whole"))
    return t.crossJoin(F.broadcast(whole)).select("prefix_pct", "enc_pct", (F.col("enc_pct") - F.col("whole")).alias("loss"))


@query("w13_query_log_with_user_turns")
def _w13(spark, sf, cap: int = 100_000):
    """Requests of benchmark texts and of user turns. A benchmark text keeps its number; a turn has (conv_id + 1) 2**32 + turn."""
    tf = retrieval.tokens(load(spark, sf, "documents"), "doc_id", F.col("text"))
    turns = load(spark, sf, "conversations").where("role = 'user'").select(((F.col("conv_id").cast("long") + 1) * (1 << 32) + F.col("turn")).alias("query_no"), "text")
    asked = load(spark, sf, "benchmark").select(F.col("item_id").cast("long").alias("query_no"), "text").unionByName(turns)
    q = retrieval.tokens(asked, "query_no", F.col("text")).select(F.col("doc_id").alias("query_no"), "term")
    return retrieval.request_list(retrieval.top_k(retrieval.rank(q, tf)), cap)


@query("w14_appends")
def _w14(spark, sf):
    """A store of the most frequent language, to which the others are appended, one a batch: the ratio drifts, the dictionary is extended, and where it has no more room
    the store is rebuilt."""
    from ..streaming.append import Appender, Monitor

    docs = load(spark, sf, "documents").select("doc_id", "text", F.coalesce("lang", F.lit("")).alias("lang"))
    langs = [r["lang"] for r in docs.groupBy("lang").count().orderBy(F.desc("count"), "lang").collect()]  # a row a language
    base = col.as_collection(docs.where(F.col("lang") == langs[0]), "doc_id", "text")
    d = dic.build(col.with_offsets(base), dic.DictSpec(pct=2.0, s=512))
    extra = max(4096, len(d.data) // 8)
    a = Appender(spark, scratch(spark, "append"), d, m_extra=extra, m_limit=len(d.data) + extra, monitor=Monitor(tau=0.5, weight=1.0))
    for k, lang in enumerate(langs):
        a.write_batch(docs.where(F.col("lang") == lang).drop("lang"), k)
        if a.log and a.log[-1]["action"] == "rebuild":
            whole = col.as_collection(docs.where(F.col("lang").isin(langs[: k + 1])), "doc_id", "text")
            a.rebuild(whole, dic.DictSpec(pct=2.0, s=512))
    return spark.createDataFrame([(x["batch"], x["ratio"], x["action"], x["epoch"], x["dict_version"]) for x in a.log], "batch int, ratio double, action string, epoch int, dict_version int")


@query("w15_stream_gain")
def _w15(spark, sf):
    """Bytes of positions and lengths under U, V, Z, the interleaved form, and one zlib stream over all documents of a block."""
    p = inputs.placed(spark, sf, "documents")
    f = factorize.factorize(p, dic.build(p, dic.DictSpec(pct=2.0, s=512))).cache()
    size = lambda c, stream: factorize.recode(f, c).agg(F.sum(F.octet_length(stream)).alias("bytes"))
    parts = [size(c, s).select(F.lit(s).alias("stream"), F.lit(c).alias("codec"), "bytes") for c, s in (("UU", "pos_stream"), ("ZZ", "pos_stream"), ("UU", "len_stream"), ("VV", "len_stream"), ("ZZ", "len_stream"), ("Zi", "pos_stream"))]
    block = measures.lengths(f).groupBy(F.pmod("doc_id", F.lit(16)).alias("b"))
    for c, s in (("pos", "pos_stream"), ("len", "len_stream")):
        parts.append(block.agg(baselines.zlib_size_agg()(F.col(c)).alias("x")).agg(F.sum("x").alias("bytes")).select(F.lit(s).alias("stream"), F.lit("Zg").alias("codec"), "bytes"))
    return _table(parts)


@query("w16_equal_size")
def _w16(spark, sf):
    """Pairs of a dictionary store and a blocked store of closest size, with the bytes that a request decodes."""
    mine = codec_grid(spark, sf, "pages", sizes=(4.0, 8.0)).select("pct", "codec", "enc_pct_total")
    theirs = block_grid(spark, sf, "pages", sizes=(0, 100_000, 1_000_000)).where("codec <> 'raw'").select(F.col("codec").alias("block_codec"), "block", "enc_pct", "decoded_per_request")
    own = inputs.pages(spark, sf).agg(F.avg("n_bytes").alias("own_bytes"))
    near = mine.crossJoin(theirs).withColumn("gap", F.abs(F.col("enc_pct_total") - F.col("enc_pct")))
    best = near.groupBy("pct", "codec").agg(F.min_by(F.struct("block_codec", "block", "enc_pct", "decoded_per_request", "gap"), "gap").alias("b"), F.first("enc_pct_total").alias("enc_pct_total"))
    return best.crossJoin(own).select("pct", "codec", "enc_pct_total", "b.block_codec", "b.block", "b.enc_pct", (F.col("b.decoded_per_request") / F.col("own_bytes")).alias("read_amplification"))


@query("w16_equal_memory")
def _w16_memory(spark, sf):
    """A dictionary of some bytes against blocks of as many: what stays in memory to read is the same."""
    p, parts = inputs.placed(spark, sf, "pages"), []
    for pct in inputs.WIDE:
        d = inputs.dictionary(p, pct)
        m = len(d.data)
        cost = measures.block_cost(p.withColumn("block_id", baselines.block_number(m))).agg(F.avg("decoded_bytes").alias("decoded_per_request"))
        own = p.agg(F.avg("n_bytes").alias("decoded_per_request"))
        parts.append(measures.ratio(factorize.encode(p, d, "ZZ"), m).crossJoin(own).select(F.lit(m).alias("memory"), F.lit("dictionary ZZ").alias("store"), F.col("enc_pct_total").alias("enc_pct"), "decoded_per_request"))
        for c in ("zlib", "lzma"):
            parts.append(baselines.blocked_ratio(baselines.blocked_store(p, c, m)).crossJoin(cost).select(F.lit(m).alias("memory"), F.lit(c).alias("store"), "enc_pct", "decoded_per_request"))
    return _table(parts)


@query("m15_url_sort_effect")
def _url_effect(spark, sf):
    """Size in natural order less size in URL order, in points, of each store of pages.

    Pages get their places once an order. The grids are made side by side: while the driver sorts a dictionary, tasks squeeze blocks or factor by another one.
    """
    placed = {order: inputs.placed(spark, sf, "pages", order).cache() for order in ("natural", "url")}
    blocks = {o: lambda p=p, o=o: block_rows(p).select(F.concat_ws(" ", "codec", F.col("block").cast("string")).alias("store"), F.col("enc_pct").alias(o)) for o, p in placed.items()}
    coded = {(pct, o): lambda p=p, o=o, pct=pct: codec_rows(p, "pages", o, pct).select(F.concat_ws(" ", F.lit("dictionary"), "codec", F.col("pct").cast("string")).alias("store"), F.col("enc_pct_total").alias(o)) for pct in inputs.WIDE for o, p in placed.items()}
    for p in placed.values():
        p.count()  # kept before they are shared
    # the largest dictionaries first, the second order's blocks after them
    first, *rest = sorted(inputs.WIDE, reverse=True)
    makers = [blocks["natural"], *(coded[first, o] for o in placed), blocks["url"], *(coded[pct, o] for pct in rest for o in placed)]
    made = _side_by_side(spark, makers)
    for p in placed.values():
        p.unpersist()
    rows = [_table([t for t in made if order in t.columns]) for order in placed]
    return rows[0].join(rows[1], "store").select("store", "natural", "url", (F.col("natural") - F.col("url")).alias("gain"))


@query("w19_two_pass")
def _w19(spark, sf):
    s = baselines.two_pass_store(load(spark, sf, "pages"))
    return s.agg(F.count("*").alias("clusters"), F.sum("n_docs").alias("n_docs"), F.sum("raw_bytes").alias("raw_bytes"), F.sum(F.octet_length("payload")).alias("enc_bytes")).withColumn("enc_pct", 100.0 * F.col("enc_bytes") / F.col("raw_bytes"))


@query("w20_pruning_passes")
def _w20(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    parts = []
    for k, d, unused in dic.prune_and_refill(p, dic.build(p, dic.DictSpec(pct=2.0, s=512)), 2, 512):
        parts.append(measures.ratio(factorize.encode(p, d, "ZV"), len(d.data)).select(F.lit(k).alias("pass"), F.lit(len(d.data)).alias("m"), F.lit(unused).alias("unused_pct"), "enc_pct"))
    return _table(parts)


@query("w21_integer_codes")
def _w21(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    f = factorize.factorize(p, dic.build(p, dic.DictSpec(pct=2.0, s=512))).cache()
    return _table([factorize.recode(f, "U" + c).agg(F.sum(F.octet_length("len_stream")).alias("length_bytes")).select(F.lit(c).alias("code"), "length_bytes") for c in "UVZSP"])


@query("w22_order_independence")
def _w22(spark, sf):
    parts = []
    for order in ("natural", "url", "host", "shuffled"):
        p = inputs.placed(spark, sf, "pages", order)
        for kind in ("even", "head"):
            d = dic.build(p, dic.DictSpec(pct=2.0, s=512, kind=kind))
            parts.append(measures.ratio(factorize.encode(p, d, "ZZ"), len(d.data)).select(F.lit(order).alias("doc_order"), F.lit(kind).alias("kind"), "enc_pct"))
    return _table(parts)


@query("w23_ratio_by_slice")
def _w23(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    enc = factorize.encode(p, inputs.dictionary(p, 2.0), "ZV")
    size = F.octet_length("pos_stream") + F.octet_length("len_stream")
    rows = enc.select("doc_id", "n_bytes", size.alias("enc_bytes")).join(load(spark, sf, "documents").select("doc_id", "lang", "source"), "doc_id").join(load(spark, sf, "labels"), "doc_id", "left")
    g = rows.groupingSets([["lang"], ["source"], ["quality"], ["toxic"]], "lang", "source", "quality", "toxic")
    return g.agg(F.sum("n_bytes").alias("raw_bytes"), F.sum("enc_bytes").alias("enc_bytes"), F.grouping_id().alias("slice")).withColumn("enc_pct", 100.0 * F.col("enc_bytes") / F.greatest(F.col("raw_bytes"), F.lit(1)))


@query("w23_ratio_of_other_collections")
def _w23b(spark, sf):
    """Conversations, orders as records, and vectors as bytes (a control that does not compress)."""
    vec = load(spark, sf, "embeddings").select("vec_id", F.unhex(F.array_join(F.transform("embedding", lambda x: F.lpad(F.hex(F.floor((x + 8) * (1 << 24)).cast("long")), 8, "0")), "")).alias("b"))
    colls = {
        "conversations": col.fold(load(spark, sf, "conversations"), "conv_id", "turn", "text"),
        "records": col.record_docs(load(spark, sf, "orders"), load(spark, sf, "lineitem")),
        "vectors": col.as_collection(vec, "vec_id", "b"),
    }
    parts = []
    for name, c in colls.items():
        p = col.with_offsets(c)
        m = col.total_bytes(p) // 100
        d = dic.build(p, dic.DictSpec(m_bytes=m, s=max(64, min(512, m // 4))))
        parts.append(measures.ratio(factorize.encode(p, d, "UV"), len(d.data)).select(F.lit(name).alias("collection"), "n_docs", "raw_bytes", "enc_pct", "enc_pct_total"))
    return _table(parts)


@query("w25_copies_by_distance")
def _w25(spark, sf):
    """What a second copy costs: the coded size of copies, by distance in bytes from the copy before, against blocks that hold both or not."""
    from pyspark.sql import Window

    p = inputs.placed(spark, sf, "documents")
    enc = factorize.encode(p, inputs.dictionary(p, 2.0), "ZV").select("doc_id", (F.octet_length("pos_stream") + F.octet_length("len_stream")).alias("enc_bytes"))
    w = Window.partitionBy("h").orderBy("start_off")
    rows = p.select("doc_id", "start_off", "n_bytes", F.md5("body").alias("h")).withColumn("gap", F.col("start_off") - F.lag("start_off").over(w)).where("gap is not null").join(enc, "doc_id")
    return rows.groupBy(F.floor(F.log10("gap")).alias("log10_gap")).agg(F.count("*").alias("copies"), (100.0 * F.sum("enc_bytes") / F.sum("n_bytes")).alias("drf_pct"), F.avg((F.col("gap") < 100_000).cast("double")).alias("share_in_one_block"))


@query("w26_speed_by_size")
def _w26(spark, sf):
    """Decoded bytes and factors of a request by deciles of document size."""
    p = inputs.placed(spark, sf, "documents")
    enc = factorize.encode(p, inputs.dictionary(p, 2.0), "UV").select("doc_id", "n_bytes", "n_factors")
    edges = enc.select(F.percentile_approx("n_bytes", [i / 10 for i in range(1, 10)]).alias("e"))
    rows = enc.crossJoin(F.broadcast(edges)).withColumn("decile", F.size(F.filter("e", lambda x: x < F.col("n_bytes"))))
    return rows.groupBy("decile").agg(F.count("*").alias("n_docs"), F.avg("n_bytes").alias("decoded_bytes"), F.avg("n_factors").alias("factors"))


@query("w26_speed_by_dictionary_and_size")
def _w26_speed(spark, sf, sizes=(1.0, 4.0, 8.0)):
    """Documents and MB a second for fifths of the documents by size, and dictionary sizes; every document is asked for once."""
    p, out = inputs.placed(spark, sf, "documents").cache(), []
    edges = p.agg(F.percentile_approx("n_bytes", [0.2, 0.4, 0.6, 0.8]).alias("e")).first()["e"] or []
    sized = p.withColumn("fifth", F.size(F.filter(F.lit(edges), lambda x: x < F.col("n_bytes"))) if edges else F.lit(0)).select("doc_id", "n_bytes", "fifth").cache()
    totals = {r["fifth"]: (r["n"], r["b"]) for r in sized.groupBy("fifth").agg(F.count("*").alias("n"), F.sum("n_bytes").alias("b")).collect()}
    for pct in sizes:
        d, path = inputs.dictionary(p, pct), scratch(spark, "speed")
        store.write_store(factorize.encode(p, d, "UV"), path)
        rows = store.read_store(spark, path).join(F.broadcast(sized.select("doc_id", "fifth")) if sum(n for n, _ in totals.values()) <= store.BROADCAST_IDS else sized.select("doc_id", "fifth"), "doc_id").cache()
        rows.count()
        for k, (n, size) in sorted(totals.items()):
            seconds = min(retrieval.timed(factorize.decode_encoded(rows.where(F.col("fifth") == k), d)) for _ in range(2))
            out.append((pct, k, n, size / max(n, 1), n / seconds, size / 1e6 / seconds))
        rows.unpersist()
    return spark.createDataFrame(out, "pct double, fifth int, n_docs long, mean_bytes double, docs_per_second double, mb_per_second double")


def _asked(spark: SparkSession, sf: str, name: str, cap: int) -> DataFrame:
    """req_no, doc_id: ranked results of benchmark texts and user turns over documents or pages."""
    if name == "documents":
        return _w13(spark, sf, cap).select("req_no", "doc_id")
    tf = retrieval.tokens(load(spark, sf, "pages"), "page_id", retrieval.strip_html(F.col("html")))
    turns = load(spark, sf, "conversations").where("role = 'user'").select(((F.col("conv_id").cast("long") + 1) * (1 << 32) + F.col("turn")).alias("query_no"), "text")
    asked = load(spark, sf, "benchmark").select(F.col("item_id").cast("long").alias("query_no"), "text").unionByName(turns)
    q = retrieval.tokens(asked, "query_no", F.col("text")).select(F.col("doc_id").alias("query_no"), "term")
    return retrieval.request_list(retrieval.top_k(retrieval.rank(q, tf)), cap).select("req_no", "doc_id")


#: stores of the published tables: pair codecs, and blocks
SPEED_BLOCKS = (("raw", 0), ("zlib", 0), ("zlib", 100_000), ("zlib", 1_000_000), ("lzma", 0), ("lzma", 1_000_000))


def speed_table(spark: SparkSession, sf: str, name: str, order: str = "natural", pct: float = 4.0, requests: int = 20_000, alone: int = 1_000, runs: int = 1) -> DataFrame:
    """Size and documents a second of each store for sequential and ranked requests: as a batch, where a document or block is opened once however often it is asked
    for, and request by request, where each opens its own (``alone`` requests of the same lists)."""
    p = inputs.placed(spark, sf, name, order).cache()
    n = p.count()
    lists = {"sequential": retrieval.sequential(p, requests, n).cache(), "query_log": _asked(spark, sf, name, requests).cache()}
    few = {k: v.where(F.col("req_no") < alone).cache() for k, v in lists.items()}
    counts = {k: (lists[k].count(), few[k].count()) for k in lists}
    d, out = inputs.dictionary(p, pct), []
    f = factorize.factorize(p, d).cache()

    def measured(label: str, size: float, whole, single) -> None:
        for access in lists:
            speed = [retrieval.docs_per_second(run(rows[access]), c, runs)["dps"] if c else 0.0 for run, rows, c in ((whole, lists, counts[access][0]), (single, few, counts[access][1]))]
            out.append((name, order, label, size, access, *speed))

    for c in PAIR_CODECS:
        path = scratch(spark, "speed")
        store.write_store(factorize.recode(f, c).join(p.select("doc_id", "n_bytes"), "doc_id").withColumn("dict_version", F.lit(0)), path)
        rows = store.read_store(spark, path)
        size = measures.ratio(rows, len(d.data)).first()["enc_pct_total"]
        measured(f"dictionary {c}", size, lambda q, rows=rows: store.retrieve(rows, d, q), lambda q, rows=rows: store.retrieve_each(rows, d, q))
    for c, block in SPEED_BLOCKS:
        path = scratch(spark, "speed")
        baselines.blocked_store(p, c, block).write.parquet(path)
        rows = spark.read.parquet(path)
        size = baselines.blocked_ratio(rows).first()["enc_pct"]
        measured(f"{c} {block}", size, lambda q, rows=rows, c=c: baselines.read_blocked(rows, c, q), lambda q, rows=rows, c=c: baselines.read_blocked_each(rows, c, q))
    return spark.createDataFrame(out, "collection string, doc_order string, store string, enc_pct double, access string, batch_docs_per_second double, alone_docs_per_second double")


query("w05_w07_speeds_pages")(lambda spark, sf: speed_table(spark, sf, "pages"))
query("w06_w08_speeds_pages_url_order")(lambda spark, sf: speed_table(spark, sf, "pages", "url"))
query("w09_w10_speeds_documents")(lambda spark, sf: speed_table(spark, sf, "documents"))


def speeds(spark: SparkSession, sf: str, name: str, pct: float = 4.0, codecs=PAIR_CODECS, blocks=SPEED_BLOCKS, requests: int = 100_000, runs: int = 3) -> list[tuple[str, str, float]]:
    """(store, access, documents a second) of whole runs, scheduling included: sequential and ranked request lists of ``requests`` ids, as the paper has them."""
    p = inputs.placed(spark, sf, name).cache()
    n = p.count()
    lists = {"sequential": retrieval.sequential(p, requests, n).cache()}
    if name == "documents":
        lists["query_log"] = _query_log(spark, sf, requests).select("req_no", "doc_id").cache()
    counts = {k: v.count() for k, v in lists.items()}
    d = dic.build(p, dic.DictSpec(pct=pct, s=1024))
    f = factorize.factorize(p, d).cache()
    out = []
    for c in codecs:
        path = scratch(spark, "speed")
        enc = factorize.recode(f, c).join(p.select("doc_id", "n_bytes"), "doc_id").withColumn("dict_version", F.lit(0))
        store.write_store(enc, path)
        for access, req in lists.items():
            out.append((c, access, retrieval.docs_per_second(store.retrieve(store.read_store(spark, path), d, req), counts[access], runs)["dps"]))
    for c, size in blocks:
        path = scratch(spark, "speed")
        baselines.blocked_store(p, c, size).write.parquet(path)
        for access, req in lists.items():
            out.append((f"{c} {size}", access, retrieval.docs_per_second(baselines.read_blocked(spark.read.parquet(path), c, req), counts[access], runs)["dps"]))
    return out


@query("measure_position_skew")
def _skew(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    return measures.position_skew(factorize.factorize(p, inputs.dictionary(p, 2.0)))


@query("measure_foreign_bytes")
def _foreign(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    n = col.total_bytes(p)
    m = n * 2 // 100
    d = dic.build(p, dic.DictSpec(m_bytes=m, s=512))
    return measures.foreign_bytes(factorize.factorize(p, d), p, 512, m // 512, n)


@query("measure_ratio_spread")
def _spread(spark, sf):
    p = inputs.placed(spark, sf, "documents")
    return measures.ratio_spread(factorize.encode(p, inputs.dictionary(p, 2.0), "ZV"))


@query("measure_memory_need")
def _memory(spark, sf):
    rows = [(pct, *measures.memory_need(int(col.total_bytes(inputs.documents(spark, sf)) * pct / 100), 1_000_000).values()) for pct in inputs.WIDE]
    return spark.createDataFrame(rows, "pct double, dictionary_decode long, dictionary_encode long, block_decode long")


@query("measure_build_time")
def _build(spark, sf):
    """Seconds of sampling and sorting, and of encoding (MB a second)."""
    import time

    p = inputs.placed(spark, sf, "documents").cache()
    n = col.total_bytes(p)
    t0 = time.perf_counter()
    d = dic.build(p, dic.DictSpec(pct=2.0, s=512))
    assert len(d.sa) == len(d.data)
    t1 = time.perf_counter()
    seconds = retrieval.timed(factorize.encode(p, d, "ZV"))
    return spark.createDataFrame([(n, t1 - t0, seconds, n / 1e6 / seconds)], "raw_bytes long, build_s double, encode_s double, encode_mb_s double")


def entry(spark: SparkSession, sf: str) -> DataFrame:
    """Pages, a 4 % dictionary of 512-byte samples, ZV: size, and whether all come back."""
    p = inputs.placed(spark, sf, "pages")
    d = inputs.dictionary(p)
    enc = factorize.encode(p, d, "ZV")
    back = factorize.decode_encoded(enc, d).select("doc_id", F.md5("body").alias("got"))
    size = F.octet_length("pos_stream") + F.octet_length("len_stream")
    rows = enc.select("doc_id", "n_bytes", size.alias("enc_bytes")).join(p.select("doc_id", F.md5("body").alias("want")), "doc_id").join(back, "doc_id")
    out = rows.agg(F.count("*").alias("n_docs"), F.sum("n_bytes").alias("raw_bytes"), F.sum("enc_bytes").alias("enc_bytes"), F.bool_and(F.col("want") == F.col("got")).alias("ok"))
    return out.select(F.lit("ZV").alias("codec"), "n_docs", "raw_bytes", "enc_bytes", (100.0 * F.col("enc_bytes") / F.col("raw_bytes")).alias("enc_pct"), "ok")
