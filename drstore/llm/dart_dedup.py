"""Near-duplicate classes by DartMinHash signatures, banded joining and an exact check.

A document is a weighted set of five-word shingles (a text of fewer words is one shingle). Every unit of an element's weight is a strip of an infinite
board; along each strip darts fall at a constant rate at pseudo-random heights, and each dart belongs to
one of ``K`` coordinates. A document sees the darts inside its own strips; coordinate by coordinate the lowest one is kept. Two documents agree in a
coordinate with a probability equal to their weighted Jaccard similarity. Only heights below (K ln K + 2 K) / weight are thrown at first, which is about
that many darts however long the text is; documents left with an empty coordinate go twice as high.

Weights are 1 (plain Jaccard) and, for documents that repeat shingles, also the counts, in one space of signatures. Two documents are linked if either
similarity reaches ``threshold``. Equal texts are one node from the start. Signatures are cut into ``BANDS`` bands of ``ROWS``; for each
band value the most connected document is compared with all others, exactly, on the sets. Where documents of a band value then still lie in
different components, those outside its largest one are joined exactly with the others by their rarest shingles (a prefix join): no cap on partners, and the
members of a large group of copies are not compared with each other.
At the threshold a pair shares no band with probability (1 - threshold^ROWS)^BANDS, 3e-6.

Nodes are 64-bit hashes of texts. Null text is empty text; texts without words are linked to equal texts only. A class is named by its least doc_id (null
if all are null). Repeated rows and repeated doc_ids are rows of their own; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import components, shared
from . import textkit as tk

SHINGLE = 5
ROWS, BANDS = 4, 24
K = ROWS * BANDS
_POISSON = np.cumsum([np.exp(-1.0) / float(np.prod(np.arange(1, k + 1))) for k in range(12)])
_COUNT_AT = np.array([min(int(p * 2.0**32), 2**32 - 1) for p in _POISSON], np.uint64)


def shingles(s: tk.Slab, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document) of every shingle, in order of documents."""
    start, end = s.words()
    cuts = s.per_doc(start)
    h = s.hash(start, end)
    first, doc = tk.windows(cuts, k)
    code = tk.rolling(h, k)[first] if len(first) else np.empty(0, np.uint64)
    size = np.diff(cuts)
    for n in range(1, k):
        few = np.flatnonzero(size == n)
        if len(few):
            code = np.concatenate([code, tk.rolling(h, n)[cuts[few]] + np.uint64(n)])
            doc = np.concatenate([doc, few])
    order = np.argsort(doc, kind="stable")
    return code[order], doc[order]


def _darts(cell: np.ndarray, doc: np.ndarray, low: np.ndarray, high: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Darts in the unit heights low..high-1 (by document) of each cell: (document * K + coordinate, height, identity)."""
    strips = (high - low)[doc]
    at = np.repeat(np.arange(len(cell)), strips)
    level = np.arange(len(at)) - np.repeat(np.cumsum(strips) - strips, strips) + low[doc][at]
    seed = tk.mix(cell[at] + level.astype(np.uint64) * np.uint64(0xA24BAED4963EE407))
    count = np.searchsorted(_COUNT_AT, seed >> np.uint64(32), side="right")
    which = np.repeat(np.arange(len(at)), count)
    number = np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count)
    dart = tk.mix(seed[which] ^ (np.uint64(0xD1B54A32D192ED03) * (number + 1).astype(np.uint64)))
    height = level[which] + (dart >> np.uint64(40)).astype(float) / 2.0**24
    slot = doc[at][which] * K + ((dart & np.uint64(0xFFFFFFFF)) * np.uint64(K) >> np.uint64(32)).astype(np.int64)
    return slot, height, tk.mix(dart)


def signatures(cell: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    """(n, K): the identity of the lowest dart of each coordinate, 0 for documents without cells. Cells are sorted by document."""
    weight = np.bincount(doc, minlength=n)
    best = np.full(n * K, np.inf)
    who = np.zeros(n * K, np.uint64)
    low = np.zeros(n, np.int64)
    high = np.where(weight > 0, np.ceil((K * np.log(K) + 2 * K) / np.maximum(weight, 1)), 0).astype(np.int64)
    while high.max(initial=0) > 0:
        slot, height, ident = _darts(cell, doc, low, high, n)
        order = np.lexsort((height, slot))
        slot, height, ident = slot[order], height[order], ident[order]
        lead = np.ones(len(slot), bool)
        lead[1:] = slot[1:] != slot[:-1]
        slot, height, ident = slot[lead], height[lead], ident[lead]
        lower = height < best[slot]
        best[slot[lower]], who[slot[lower]] = height[lower], ident[lower]
        open_ = np.isinf(best.reshape(n, K)).any(1) & (weight > 0)
        low = np.where(open_, np.maximum(high, low), 0)
        high = np.where(open_, 2 * np.maximum(high, low), 0)
        low = np.minimum(low, high)
    return who.reshape(n, K)


def bands(sig: np.ndarray) -> np.ndarray:
    out = np.zeros((len(sig), BANDS), np.uint64)
    for r in range(ROWS):
        out = tk.mix(out * np.uint64(0x9FB21C651E98DF25) + sig[:, r::ROWS])
    return tk.mix(out + np.arange(1, BANDS + 1, dtype=np.uint64))


def _copies(code: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """How many equal shingles of the same document come before each."""
    order = np.lexsort((code, doc))
    same = np.zeros(len(code), bool)
    same[1:] = (code[order][1:] == code[order][:-1]) & (doc[order][1:] == doc[order][:-1])
    at = np.arange(len(code))
    begin = np.maximum.accumulate(np.where(same, 0, at))
    out = np.empty(len(code), np.int64)
    out[order] = at - begin
    return out


def slab_bands(s: tk.Slab) -> list[np.ndarray]:
    """Distinct band values of each document."""
    code, doc = shingles(s)
    copy = _copies(code, doc)
    one = copy == 0
    out = list(bands(signatures(tk.mix(code[one]), doc[one], s.n)))
    repeats = np.bincount(doc[~one], minlength=s.n) > 0
    if repeats.any():
        pick = repeats[doc]
        number = np.cumsum(repeats) - 1
        cell = tk.mix(code[pick]) + copy[pick].astype(np.uint64) * np.uint64(0x8CB92BA72F3D8DD7)
        cell = np.where(copy[pick] == 0, tk.mix(code[pick]), tk.mix(cell))
        extra = bands(signatures(cell, number[doc[pick]], int(repeats.sum())))
        for d, e in zip(np.flatnonzero(repeats).tolist(), extra, strict=True):
            out[d] = np.unique(np.concatenate([out[d], e]))
    empty = np.bincount(doc, minlength=s.n) == 0
    for d in np.flatnonzero(empty).tolist():
        out[d] = np.empty(0, np.uint64)
    return out


@tk.tidy
def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for i, j, s in tk.slabs(b.column(2)):
            rows = slab_bands(s)
            cuts = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int32)
            flat = np.concatenate(rows).view(np.int64) if rows else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), b.column(1).slice(i, j - i), pa.ListArray.from_arrays(pa.array(cuts), pa.array(flat))], names=["doc_id", "node", "bands"])


@tk.tidy
def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node, set: sorted 64-bit shingles (copies of one follow it as hashes of their own, after the distinct ones), n_distinct."""
    for b in batches:
        for i, j, s in tk.slabs(b.column(1)):
            code, doc = shingles(s)
            copy = _copies(code, doc)
            short = np.where(copy == 0, code, tk.mix(code + copy.astype(np.uint64) * np.uint64(0x8CB92BA72F3D8DD7))) >> np.uint64(24)
            order = np.lexsort((short, copy > 0, doc))
            cuts = np.searchsorted(doc, np.arange(s.n + 1))
            short = short[order].astype("<u8")
            distinct = np.bincount(doc[copy == 0], minlength=s.n)
            # 40 bits each
            packed = short.view(np.uint8).reshape(-1, 8)[:, :5]
            yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array([packed[x:y].tobytes() for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)], pa.binary()), pa.array(distinct.astype(np.int32))], names=["node", "set", "n"])


def _unpack(blob: bytes) -> np.ndarray:
    a = np.frombuffer(blob, np.uint8).reshape(-1, 5)
    out = np.zeros((len(a), 8), np.uint8)
    out[:, :5] = a
    return out.view("<u8").ravel()


def _jaccard(a: np.ndarray, b: np.ndarray) -> float:
    if not len(a) and not len(b):
        return 1.0
    i = np.searchsorted(b, a)
    both = int((b[np.minimum(i, len(b) - 1)] == a).sum()) if len(b) else 0
    return both / (len(a) + len(b) - both)


def similarity(a: bytes, na: int, b: bytes, nb: int) -> float:
    """The greater of plain and count-weighted Jaccard similarity of two packed sets."""
    x, y = _unpack(a), _unpack(b)
    plain = _jaccard(x[:na], y[:nb])
    if na == len(x) and nb == len(y):
        return plain
    return max(plain, _jaccard(np.sort(x), np.sort(y)))


def _check(threshold: float):
    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            c = [b.column(k).to_pylist() for k in range(6)]
            ok = [similarity(sa, na, sb, nb) >= threshold for sa, na, sb, nb in zip(*c[2:], strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(ok, pa.bool_())), b.column(1).filter(pa.array(ok, pa.bool_()))], names=["a", "b"])

    return run


def rows_of(docs: DataFrame, text: str = "text") -> DataFrame:
    t = F.coalesce(docs[text].cast("string"), F.lit(""))
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.xxhash64(t).alias("node"), t.alias("text"))


def sets_of(docs: DataFrame, nodes: DataFrame) -> DataFrame:
    """node, set, n: the packed sets of some distinct nodes. Tasks send one of the copies of a text that they hold."""
    texts = rows_of(docs).groupBy("node").agg(F.first("text").alias("text"))
    return texts.join(nodes, "node").select("node", "text").mapInArrow(_sets, "node long, set binary, n int")


def _salted(pairs: DataFrame, sets: DataFrame, hot: DataFrame, side: str, other: str) -> DataFrame:
    """pairs with the set of one side. hot: node, parts; the set of such a node goes to that many tasks, its pairs are dealt to them."""
    parts = F.coalesce("parts", F.lit(1).cast("long"))
    left = pairs.join(F.broadcast(hot.withColumnRenamed("node", side)), side, "left").withColumn("part", F.pmod(F.xxhash64(other), parts)).drop("parts")
    right = sets.join(F.broadcast(hot), "node", "left").withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), parts - 1)))
    return left.join(right.select(F.col("node").alias(side), "part", F.col("set").alias(f"s{side}"), F.col("n").alias(f"n{side}")), [side, "part"]).drop("part")


#: Pairs of one node from which on its set goes to several tasks, unless one in ``shared.HOT_SHARE`` of all pairs is more.
HOT_PAIRS = 100


def verified(sets: DataFrame, pairs: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, b) of nodes whose texts reach the threshold."""
    pairs = shared.keep(pairs, "pairs")
    limit = max(pairs.count() // shared.HOT_SHARE, HOT_PAIRS)
    # fewer than 2 * HOT_SHARE nodes
    hot = pairs.select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count("*").alias("n")).where(F.col("n") > limit)
    hot = shared.keep(hot.select("node", F.ceil(F.col("n") / limit).alias("parts")), "hubs")
    full = _salted(_salted(pairs, sets, hot, "a", "b"), sets, hot, "b", "a").select("a", "b", "sa", "na", "sb", "nb")
    return full.mapInArrow(_check(threshold), "a long, b long")


@tk.tidy
def _elements(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(counted, element, node, size): the distinct shingles of each set and, apart, its shingles with their copies."""
    for b in batches:
        for i in range(0, b.num_rows, 256):
            part = b.slice(i, 256)
            node, n = part.column(0).to_numpy(), part.column(2).to_numpy()
            items = [_unpack(x) for x in part.column(1).to_pylist()]
            for counted, lists in ((False, [x[:k] for x, k in zip(items, n.tolist(), strict=True)]), (True, items)):
                size = np.array([len(x) for x in lists])
                flat = np.concatenate(lists) if lists else np.empty(0, np.uint64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(flat), counted)), pa.array(flat.astype(np.int64)), pa.array(np.repeat(node, size)), pa.array(np.repeat(size, size))], names=["counted", "element", "node", "size"])


def prefix_pairs(sets: DataFrame, nodes: DataFrame, threshold: float) -> DataFrame:
    """(a, b): pairs of different labels that can reach the threshold and of which one is on the fringe. nodes: node, label, fringe.

    Elements are put in one order, the rarest first. Two sets of sizes x and y that reach the threshold share at least t (x + y) / (1 + t) elements, so the
    first that they share is near enough to the beginning of both; only such places are joined.
    """
    e = sets.join(nodes.select("node"), "node", "left_semi").mapInArrow(_elements, "counted boolean, element long, node long, size long")
    often = e.groupBy("counted", "element").agg(F.count("*").alias("often"))
    w = Window.partitionBy("node", "counted").orderBy("often", "element")
    placed = e.join(often.where("often > 1"), ["counted", "element"])
    # what a set has for itself comes before the rest, so places follow from their number
    own = e.join(often.where("often = 1"), ["counted", "element"], "left_semi").groupBy("counted", "node").agg(F.count("*").alias("own"))
    placed = placed.withColumn("r", F.row_number().over(w)).join(own, ["counted", "node"], "left").withColumn("r", F.col("r") + F.coalesce("own", F.lit(0)))
    placed = placed.where(F.col("r") <= F.col("size") - F.ceil(threshold * F.col("size") - 1e-9) + 1).join(nodes, "node")
    placed = shared.keep(placed.select("counted", "element", "node", "size", "r", "label", "fringe"), "places")
    f, g = placed.where("fringe").alias("f"), placed.alias("g")
    least = F.ceil(threshold * (F.col("f.size") + F.col("g.size")) / (1 + threshold) - 1e-9)
    near = (F.col("f.r") <= F.col("f.size") - least + 1) & (F.col("g.r") <= F.col("g.size") - least + 1)
    hit = (F.col("f.counted") == F.col("g.counted")) & (F.col("f.element") == F.col("g.element")) & (F.col("f.label") != F.col("g.label")) & near
    return f.join(g, hit).select(F.least("f.node", "g.node").alias("a"), F.greatest("f.node", "g.node").alias("b")).distinct()


def classes(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """doc_id, node, class_node (least node of the class), class_id (least doc_id of the class), class_size (documents)."""
    signed = shared.keep(rows_of(docs).mapInArrow(_sign, "doc_id long, node long, bands array<long>"), "signatures")
    alike = shared.keep(signed.groupBy("node").agg(F.first("bands").alias("bands"), F.min("doc_id").alias("least"), F.count("*").alias("copies")), "nodes")
    member = alike.select("node", F.explode("bands").alias("key"))
    size = shared.keep(member.groupBy("key").agg(F.count("*").alias("size")).where("size > 1").withColumn("often", F.col("size")), "sizes")
    member = shared.keep(shared.meet(member, size, "key", "often", BANDS * alike.count()), "members")
    central = member.groupBy("node").agg(F.sum("size").alias("central"))
    sets = shared.keep(sets_of(docs, central.select("node")), "sets")
    member = shared.keep(member.join(central, "node"), "members")
    # every member of a band value against the most connected one
    total = member.count()
    lead = member.groupBy("key").agg(F.max(F.struct("central", "node")).alias("m"), F.count("*").alias("often")).select("key", F.col("m.node").alias("leader"), "often")
    pairs = shared.meet(member, shared.keep(lead, "leaders"), "key", "often", total).where("node <> leader").select(F.least("node", "leader").alias("a"), F.greatest("node", "leader").alias("b")).distinct()
    edges = shared.keep(verified(sets, pairs, threshold), "links")
    label = components.components(edges)
    # what is left: band values with members in different components
    live = member.where("size > 2").select("key", "size", "node").join(label, "node", "left").withColumn("label", F.coalesce("label", "node"))
    live = shared.keep(live, "live")
    share = live.groupBy("key", "label").agg(F.count("*").alias("c"))
    top = share.groupBy("key").agg(F.max(F.struct("c", "label")).alias("m"), F.count("*").alias("labels"), F.sum("c").alias("often")).where("labels > 1")
    top = shared.keep(top.select("key", F.col("m.label").alias("top"), "often"), "tops")
    nodes = shared.meet(live, top, "key", "often", total).groupBy("node", "label").agg(F.max(F.col("label") != F.col("top")).alias("fringe"))
    nodes = shared.keep(nodes, "fringe")
    if nodes.limit(1).count():
        pairs = prefix_pairs(sets, nodes, threshold)
        edges = edges.unionByName(shared.keep(verified(sets, pairs, threshold), "links"))
        label = components.components(edges)
    # texts first, then rows: what a large group has in common is sent to every task, not gathered in one
    texts = alike.select("node", "least", "copies").join(label, "node", "left")
    texts = shared.keep(texts.withColumn("label", F.coalesce("label", "node")), "texts")
    names = texts.groupBy("label").agg(F.min("least").alias("class_id"), F.sum("copies").alias("class_size"), F.count("*").alias("texts"))
    named = shared.meet(texts, shared.keep(names, "names"), "label", "texts", texts.count())
    named = shared.keep(named.select("node", F.col("label").alias("class_node"), "class_id", "class_size", "copies"), "classes")
    return shared.meet(signed.select("doc_id", "node"), named, "node", "copies", signed.count()).select("doc_id", "node", "class_node", "class_id", "class_size")


def keep_one(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """The documents less all but one of each class: the one with the least doc_id (null before all), then the least text hash; repeated rows once."""
    place, node = shared.free_name(docs, "place"), shared.free_name(docs, "node")
    at = lambda c: F.struct(c.isNotNull().alias("known"), F.coalesce(c, F.lit(0).cast("long")).alias("id"))
    found = classes(docs, threshold).select("class_node", F.struct(at(F.col("doc_id")).alias(place), F.col("node").alias(node)).alias("m"))
    # a chosen row and how often it is repeated
    rows = shared.keep(found.groupBy("class_node", "m").agg(F.count("*").alias("n")), "places")
    chosen = rows.groupBy("class_node").agg(F.min(F.struct("m", "n")).alias("c")).select(F.col("c.m").alias("m"), F.col("c.n").alias("n"))
    own = F.struct(at(docs["doc_id"].cast("long")).alias(place), F.xxhash64(F.coalesce(docs["text"].cast("string"), F.lit(""))).alias(node))
    key = shared.free_name(docs, "m")
    kept = shared.meet(docs.withColumn(key, own), shared.keep(chosen.withColumnRenamed("m", key), "chosen"), key, "n", docs.count(), semi=True)
    return kept.dropDuplicates([key]).select(*(kept[f"`{c}`"] for c in docs.columns))
