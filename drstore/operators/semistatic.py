"""Two-pass codes with a fixed model: Huffman over characters and words, byte-wise variants, and dense codes.

The first pass counts symbols with one distributed aggregation; code lengths come from the counts alone. The model of a code over characters
is small; word models can be as large as the collection's vocabulary, so ranks and dense codewords are computed in tables, and only
the trees of Huffman codes are built on the driver, over the table of distinct counts.
"""

from __future__ import annotations

import heapq
from collections import Counter
from collections.abc import Iterator
from itertools import count as counter

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut, small_batches

#: words and what is between them, in turn
WORDS = r"[\p{L}\p{N}]+|[^\p{L}\p{N}]+"


def _parts(kind: str, text: str) -> Column:
    return F.expr(f"regexp_extract_all(coalesce({text}, ''), '{WORDS if kind == 'word' else '(?s).'}', 0)".replace("\\", "\\\\"))


def symbols(texts: DataFrame, kind: str, text: str = "text") -> DataFrame:
    """doc_id, seq, symbol: characters, or words and non-words."""
    return listed(symbol_lists(texts, kind, text))


def frequencies(sym: DataFrame) -> DataFrame:
    """symbol, freq."""
    return sym.groupBy("symbol").agg(F.count("*").alias("freq"))


def symbol_lists(texts: DataFrame, kind: str, text: str = "text") -> DataFrame:
    """doc_id, symbols: the same as one list for each row."""
    return texts.select("doc_id", _parts(kind, text).alias("symbols"))


def listed(lists: DataFrame) -> DataFrame:
    """doc_id, seq, symbol of lists."""
    return lists.select("doc_id", F.posexplode("symbols").alias("seq", "symbol"))


#: Symbols among which the most frequent pairs are looked for first, for each pair that is wanted.
FIRST = 4


def best_pairs(lists: DataFrame, freq: DataFrame, top: int) -> list[tuple[str, str]]:
    """The ``top`` most frequent pairs of neighbours that come twice or more (ties by their symbols).

    A pair is no more frequent than either symbol. So pairs of the most frequent symbols are counted, and these are enough if the last pair wanted comes more often
    than any symbol left out; else four times as many symbols are taken. Only symbols and few pairs are shuffled, not all pairs.
    """
    m = FIRST * top
    while True:
        rows = freq.where("freq > 1").orderBy(F.desc("freq"), "symbol").limit(m + 1).collect()
        among, left_out = {r["symbol"] for r in rows[:m]}, rows[m]["freq"] if len(rows) > m else 1

        def run(batches: Iterator[pa.RecordBatch], among=among) -> Iterator[pa.RecordBatch]:
            seen: Counter = Counter()
            for b in batches:
                for at in range(0, b.num_rows, LISTS):
                    for x in b.column(0).slice(at, LISTS).to_pylist():
                        seen.update(p for p in zip(x or (), (x or ())[1:], strict=False) if p[0] in among and p[1] in among)
                if len(seen) > 500_000:
                    yield counted(seen)
                    seen.clear()
            yield counted(seen)

        def counted(seen: Counter) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in seen], pa.string()), pa.array([p[1] for p in seen], pa.string()), pa.array(list(seen.values()), pa.int64())], names=["a", "b", "c"])

        small_batches(lists.sparkSession)
        near = lists.select("symbols").mapInArrow(run, "a string, b string, c long").groupBy("a", "b").agg(F.sum("c").alias("c")).where("c > 1")
        best = near.orderBy(F.desc("c"), "a", "b").limit(top).collect()
        if left_out <= 1 or (len(best) == top and best[-1]["c"] > left_out):
            return [(r["a"], r["b"]) for r in best]
        m *= 4


def pair_lists(lists: DataFrame, top: int, freq: DataFrame | None = None) -> DataFrame:
    """Words and word pairs: the ``top`` most frequent pairs of neighbours become symbols, left to right without overlap. doc_id, symbols.

    freq: the lists' ``frequencies``, where they are there already.
    """
    hits = set(best_pairs(lists, cut(frequencies(listed(lists))) if freq is None else freq, top))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, LISTS):
                part = b.slice(at, LISTS)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([_joined(x or [], hits) for x in part.column(1).to_pylist()], pa.list_(pa.string()))], names=["doc_id", "symbols"])

    small_batches(lists.sparkSession)
    return lists.mapInArrow(run, f"doc_id {lists.schema['doc_id'].dataType.simpleString()}, symbols array<string>")


#: Lists that are taken apart at once.
LISTS = 64


def _joined(x: list[str], hits: set[tuple[str, str]]) -> list[str]:
    out, i, last = [], 0, len(x) - 1
    while i < last:
        if (x[i], x[i + 1]) in hits:
            out.append(x[i] + x[i + 1])
            i += 2
        else:
            out.append(x[i])
            i += 1
    return out + x[i:]


def phrase_lists(lists: DataFrame, top: int, longest: int = 4) -> DataFrame:
    """Phrases: pairs are joined again and again, so symbols grow to ``2^rounds`` words. Texts are read again in each round, nothing is stored."""
    out, size = lists, 1
    while size < longest:
        out, size = pair_lists(out, top), 2 * size
    return out


def vocabulary_profile(sym: DataFrame) -> DataFrame:
    """symbols, singletons, singleton_non_words, vocabulary_bytes, occurrences."""
    f = frequencies(sym)
    non_word = ~F.col("symbol").rlike(r"^[\p{L}\p{N}]")
    return f.agg(
        F.count("*").alias("symbols"),
        F.count_if(F.col("freq") == 1).alias("singletons"),
        F.count_if((F.col("freq") == 1) & non_word).alias("singleton_non_words"),
        F.sum(F.octet_length("symbol")).alias("vocabulary_bytes"),
        F.sum("freq").alias("occurrences"),
    )


# -- Huffman


def huffman_lengths(freq: dict, arity: int = 2) -> dict:
    """Code length of each symbol. With an arity over 2 the first merge takes as many as leave full nodes above."""
    if len(freq) <= 1:
        return {s: 1 for s in freq}
    tie = counter()
    heap = [(f, next(tie), [s]) for s, f in sorted(freq.items(), key=lambda x: (x[1], str(x[0])))]
    heapq.heapify(heap)
    depth = dict.fromkeys(freq, 0)
    first = (len(heap) - 1) % (arity - 1)
    size = first + 1 if first else arity
    while len(heap) > 1:
        total, members = 0, []
        for _ in range(min(size, len(heap))):
            f, _, group = heapq.heappop(heap)
            total += f
            members += group
        for s in members:
            depth[s] += 1
        heapq.heappush(heap, (total, next(tie), members))
        size = arity
    return depth


def canonical_codes(lengths: dict) -> dict:
    """Bit strings of a code with these lengths, in order of length and symbol."""
    code, last, out = 0, 0, {}
    for s, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        code <<= n - last
        out[s], last = format(code, f"0{n}b"), n
        code += 1
    return out


def huffman_cost(freq: DataFrame, arity: int = 2, digit_bits: int = 1) -> DataFrame:
    """symbols, occurrences, coded_bits: for one bit digits (arity 2), byte digits (256), or tagged bytes (128).

    The tree depends on counts only, so the driver needs the table (count, symbols with it), not the vocabulary.
    """
    table = {r["freq"]: r["n"] for r in freq.groupBy("freq").agg(F.count("*").alias("n")).collect()}
    bits = sum(f * n for f, n in _lengths_by_count(table, arity)) * digit_bits
    total, kinds = sum(f * n for f, n in table.items()), sum(table.values())
    return freq.sparkSession.createDataFrame([(kinds, total, bits)], "symbols long, occurrences long, coded_bits long")


def _lengths_by_count(table: dict[int, int], arity: int) -> list[tuple[int, int]]:
    """Weights of the inner nodes as (weight, how many): their sum is the coded size. Equal weights are merged in bulk."""
    heap = sorted(table.items())
    heapq.heapify(heap)
    kinds = sum(table.values())
    if kinds <= 1:
        return [(f, n) for f, n in table.items()]
    pool: Counter = Counter()
    for f, n in heap:
        pool[f] += n
    order = list(pool)
    heapq.heapify(order)
    first = (kinds - 1) % (arity - 1)
    size, left, inner = (first + 1 if first else arity), kinds, []
    while left > 1:
        f = order[0]
        if pool[f] >= 2 * size and size == arity:
            k = pool[f] // arity
            pool[f] -= k * arity
            left -= k * (arity - 1)
            inner.append((arity * f, k))
            _put(pool, order, arity * f, k)
        else:
            weight, need = 0, min(size, left)
            left -= need - 1
            while need:
                f = order[0]
                take = min(need, pool[f])
                weight += f * take
                pool[f] -= take
                need -= take
                if not pool[f]:
                    heapq.heappop(order)
                    del pool[f]
            inner.append((weight, 1))
            _put(pool, order, weight, 1)
            size = arity
        while order and not pool.get(order[0]):
            pool.pop(heapq.heappop(order), None)
    return inner


def _put(pool: Counter, order: list[int], weight: int, n: int) -> None:
    if weight not in pool:
        heapq.heappush(order, weight)
    pool[weight] += n


def tagged_codes(lengths: dict) -> dict[object, bytes]:
    """Byte codewords with seven bits each from a code of arity 128; the first byte of a codeword has its high bit set."""
    code, last, out = 0, 0, {}
    for s, n in sorted(lengths.items(), key=lambda x: (x[1], str(x[0]))):
        code <<= 7 * (n - last)
        digits = [(code >> (7 * (n - 1 - i))) & 127 for i in range(n)]
        out[s], last = bytes([digits[0] | 128, *digits[1:]]), n
        code += 1
    return out


def search_tagged(coded: bytes, codes: dict, pattern: list) -> list[int]:
    """Places in coded text where the pattern's symbols begin, without decoding: codewords begin with a tagged byte, so a match there is one."""
    want, out, at = b"".join(codes[s] for s in pattern), [], -1
    while (at := coded.find(want, at + 1)) >= 0:
        end = at + len(want)
        if end == len(coded) or coded[end] & 128:
            out.append(at)
    return out


# -- dense codes


def dense_code(rank: int) -> bytes:
    """Codeword of a 0-based rank: digits of base 128, the last byte has its high bit set."""
    size, first = 1, 0
    while rank - first >= 128**size:
        first += 128**size
        size += 1
    v, out = rank - first, []
    for i in range(size):
        out.append(v >> (7 * (size - 1 - i)) & 127)
    out[-1] |= 128
    return bytes(out)


def undense(coded: bytes) -> list[int]:
    out, v, first, size = [], 0, 0, 0
    for b in coded:
        if size:
            first += 128**size
        v = v * 128 + (b & 127)
        size += 1
        if b & 128:
            out.append(v + first)
            v, first, size = 0, 0, 0
    return out


def dense_length(rank: Column) -> Column:
    """Bytes of a rank's codeword, for every 64-bit rank."""
    first = [sum(128**k for k in range(1, n + 1)) for n in range(1, 9)]  # ranks that have up to n bytes
    return sum((F.when(rank >= F.lit(x), 1).otherwise(0) for x in first), F.lit(1))


def ranked(freq: DataFrame) -> DataFrame:
    """symbol, freq, rank by falling frequency (ties by symbol), in key ranges without a window over everything."""
    ranged = cut(freq.repartitionByRange(F.desc("freq"), F.asc("symbol")).withColumn("part", F.spark_partition_id()))
    before, total = {}, 0
    for r in ranged.groupBy("part").count().orderBy("part").collect():  # one row a partition
        before[r["part"]] = total
        total += r["count"]
    if not before:
        return freq.withColumn("rank", F.lit(0).cast("long"))
    base = F.create_map(*(F.lit(x) for kv in before.items() for x in kv))[F.col("part")]
    w = Window.partitionBy("part").orderBy(F.desc("freq"), F.asc("symbol"))
    return ranged.select("symbol", "freq", (base + F.row_number().over(w) - 1).cast("long").alias("rank"))


def dense_cost(freq: DataFrame) -> DataFrame:
    """symbols, occurrences, coded_bytes, vocabulary_bytes."""
    r = ranked(freq)
    return r.agg(F.count("*").alias("symbols"), F.sum("freq").alias("occurrences"), F.sum(F.col("freq") * dense_length(F.col("rank"))).alias("coded_bytes"), F.sum(F.octet_length("symbol")).alias("vocabulary_bytes"))


def dynamic_dense(sym: list[str], light: bool = False) -> bytes:
    """One pass over a document: ranks change as counts grow, and a new word is sent in full after the escape (the next free rank).

    ``light``: a word moves only when that shortens its codeword, so the other side has less to follow.
    """
    order: list[str] = []
    place: dict[str, int] = {}
    seen: Counter = Counter()
    out = bytearray()
    for s in sym:
        if s not in place:
            raw = s.encode()
            out += dense_code(len(order)) + len(raw).to_bytes(4, "little") + raw
            place[s] = len(order)
            order.append(s)
        else:
            out += dense_code(place[s])
        _promote(s, order, place, seen, light)
    return bytes(out)


def _promote(s: str, order: list[str], place: dict[str, int], seen: Counter, light: bool) -> None:
    i = place[s]
    before = seen[s]
    seen[s] += 1
    low, high = 0, i  # the first with the old count: counts fall along the order, or nearly so in the light form
    if light:
        size = len(dense_code(i))
        if size == 1:
            return
        target = sum(128**k for k in range(1, size - 1))
        j = max(target, sum(128**k for k in range(1, size)) - 1)
        if seen[order[j]] >= seen[s]:
            return
    else:
        while low < high:
            mid = (low + high) // 2
            if seen[order[mid]] <= before:
                high = mid
            else:
                low = mid + 1
        j = low
    if j < i:
        other = order[j]
        order[j], order[i] = s, other
        place[s], place[other] = j, i


def undo_dynamic_dense(coded: bytes, light: bool = False) -> list[str]:
    order: list[str] = []
    place: dict[str, int] = {}
    seen: Counter = Counter()
    out, at = [], 0
    while at < len(coded):
        end = at
        while not coded[end] & 128:
            end += 1
        (rank,) = undense(coded[at : end + 1])
        at = end + 1
        if rank == len(order):
            n = int.from_bytes(coded[at : at + 4], "little")
            s = coded[at + 4 : at + 4 + n].decode()
            at += 4 + n
            place[s] = len(order)
            order.append(s)
        else:
            s = order[rank]
        out.append(s)
        _promote(s, order, place, seen, light)
    return out
