"""Scoring by an n-gram model whose tries are coded by Elias-Fano.

Words are bytes between separators with A-Z lowered; a text is its words and one end token. The model interpolates orders 1 to ``ORDER`` with absolute
discounts: p_n(w | c) = max(count(c w) - D, 0) / count(c) + D kinds(c) / count(c) p_(n-1)(w | shorter c); the first order keeps D kinds / N for
unknown words. Every level of a trie has a sorted sequence of context codes, monotone pointers from contexts to their successors, and the successors' codes
in one monotone sequence (context rank above word code), all Elias-Fano coded, and 8-bit codes of the discounted probability of
each successor and of the back-off weight of each context. A query finds its context, follows its two pointers, and searches the word between them; many
queries go through these steps together, on the mapped levels as they are coded (``elias_fano``). The first level is the words' codes with their counts.

Counting and querying are one exchange. Each block of documents (kept as compressed files in the shared folder) sends its distinct n-grams, with how often training documents
hold them, to shards of contexts; a shard adds the counts, writes its tries to the shared folder, maps them, and answers each block in
the order of its questions; blocks put the answers together. So no task or driver holds the model, and what is gathered grows with the corpus. The
number of shards follows the number of training tokens, ``SHARD_TOKENS`` each.
Contexts that hold more than 1/``HOT_UNIGRAM`` (one word) or 1/``HOT_BIGRAM`` (two words) of the tokens, a list of bounded size, are split by successor. No shard
knows their totals, so their trie holds 16-bit codes of discounted counts; the totals, one row for each, are added up and sent to the blocks.

Codes: inside a shard contexts have 30 bits, words 28, and after two words as many as the largest context that is not split may have successors, and four more.
An unseen n-gram whose code is taken is answered as a seen one; ``tests/llm`` counts how often. Counts of single words are
exact but for collisions of hashes of 44 bits inside a shard.

Null text is empty text: its only token is the end. Null doc_id: scored, held_out is false, not learned from. Repeated rows are learned from and scored
as rows of their own; an empty table gives an empty result. A text longer than a block is a block of its own, whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import shared
from . import textkit as tk
from .elias_fano import EliasFano
from .run_length_dedup import _by_shard, hash_text

ORDER = 3
DISCOUNT = (0.5, 0.7, 0.8)
HOT_UNIGRAM, HOT_BIGRAM = 500, 2000
BLOCK_BYTES = 6 << 20
BEGIN, END = np.uint64(0x5851F42D4C957F2D), np.uint64(0x14057B7EF767814F)
LOG_STEP = 0.03  # of 8-bit codes of log10 values: code k > 0 is -LOG_STEP (k - 1), 0 is zero probability


def quantise(p: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore"):
        k = 1 + np.rint(-np.log10(p) / LOG_STEP)
    return np.where(p > 0, np.clip(k, 1, 255), 0).astype(np.uint8)


_VALUE = np.concatenate([[0.0], 10.0 ** (-LOG_STEP * np.arange(255))])
#: discounted counts of split contexts: code k > 0 is 10^(FINE_STEP k - 1), up to 10^15
FINE_STEP = 16 / 65535


def quantise_count(c: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore"):
        k = np.rint((np.log10(c) + 1) / FINE_STEP)
    return np.where(c > 0, np.clip(k, 1, 65535), 0).astype(np.uint16)


def _padded(a: np.ndarray) -> bytes:
    raw = a.tobytes()
    return raw + bytes(-len(raw) % 8)


#: questions that are searched together
TOGETHER = 1 << 17


class Trie:
    """One order of a shard. Codes of successors have 8 bits (probabilities) or, for split contexts, 16 (discounted counts) and no back-off weights."""

    def __init__(self, contexts: EliasFano, pointers: EliasFano, successors: EliasFano, codes: np.ndarray, backoff: np.ndarray, bits: int):
        self.contexts, self.pointers, self.successors, self.codes, self.backoff, self.bits = contexts, pointers, successors, codes, backoff, bits

    @classmethod
    def build(cls, key: np.ndarray, count: np.ndarray, bits: int, discount: float, split: bool = False) -> Trie:
        """key: sorted distinct context << bits | word; count > 0."""
        ctx = key >> np.uint64(bits)
        u, first, inverse = np.unique(ctx, return_index=True, return_inverse=True)
        relative = inverse.astype(np.uint64) << np.uint64(bits) | key & np.uint64((1 << bits) - 1)
        levels = EliasFano.build(u), EliasFano.build(np.append(first, len(key))), EliasFano.build(relative)
        held = np.maximum(count - discount, 0)
        if split:
            return cls(*levels, quantise_count(held), np.empty(0, np.uint8), bits)
        total, kinds = np.bincount(inverse, count, minlength=len(u)), np.bincount(inverse, minlength=len(u))
        return cls(*levels, quantise(held / total[inverse] if len(u) else held), quantise(np.maximum(discount * kinds / np.maximum(total, 1), 1e-7)), bits)

    def to_bytes(self) -> bytes:
        body = self.contexts.to_bytes() + self.pointers.to_bytes() + self.successors.to_bytes()
        return np.array([self.bits, self.codes.itemsize], "<i8").tobytes() + body + _padded(self.codes) + _padded(self.backoff)

    @classmethod
    def read(cls, buffer: memoryview | bytes) -> Trie:
        bits, wide = np.frombuffer(buffer, "<i8", 2).tolist()
        contexts, at = EliasFano.read(buffer, 16)
        pointers, at = EliasFano.read(buffer, at)
        successors, at = EliasFano.read(buffer, at)
        codes = np.frombuffer(buffer, np.uint16 if wide == 2 else np.uint8, successors.n, at)
        at += codes.nbytes + -codes.nbytes % 8
        return cls(contexts, pointers, successors, codes, np.frombuffer(buffer, np.uint8, contexts.n if wide == 1 else 0, at), bits)

    def answers(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(codes, back-off codes) of sorted distinct queries; 0 where the n-gram or the context is unknown."""
        p, g = np.zeros(len(key), self.codes.dtype), np.zeros(len(key), np.uint8)
        for i in range(0, len(key) if self.contexts.n else 0, TOGETHER):
            p[i : i + TOGETHER], g[i : i + TOGETHER] = self._some(key[i : i + TOGETHER])
        return p, g

    def _some(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        asked = key >> np.uint64(self.bits)
        lead = np.ones(len(key), bool)
        lead[1:] = asked[1:] != asked[:-1]
        c = asked[lead]
        rank, known = self.contexts.successor(np.zeros(len(c), np.int64), np.full(len(c), self.contexts.n), c)
        rank = rank[known]
        low, high = self.pointers.at(rank).astype(np.int64), self.pointers.at(rank + 1).astype(np.int64)
        # back from contexts to queries
        number = np.cumsum(lead) - 1
        mine = np.flatnonzero(known[number])
        of = (np.cumsum(known) - 1)[number[mine]]
        p, g = np.zeros(len(key), self.codes.dtype), np.zeros(len(key), np.uint8)
        if len(self.backoff):
            g[mine] = self.backoff[rank[of]]
        x = rank[of].astype(np.uint64) << np.uint64(self.bits) | key[mine] & np.uint64((1 << self.bits) - 1)
        place, hit = self.successors.successor(low[of], high[of], x)
        p[mine[hit]] = self.codes[place[hit]]
        return p, g


class Words:
    """The first level of a shard: words' codes and their counts, which the base scores need as they are."""

    def __init__(self, codes: EliasFano, counts: np.ndarray):
        self.codes, self.counts = codes, counts

    @classmethod
    def build(cls, key: np.ndarray, count: np.ndarray) -> Words:
        return cls(EliasFano.build(key), count.astype("<i8"))

    def to_bytes(self) -> bytes:
        return self.codes.to_bytes() + self.counts.tobytes()

    @classmethod
    def read(cls, buffer: memoryview | bytes) -> Words:
        codes, at = EliasFano.read(buffer)
        return cls(codes, np.frombuffer(buffer, "<i8", codes.n, at))

    def answers(self, key: np.ndarray) -> np.ndarray:
        out = np.zeros(len(key), np.int64)
        for i in range(0, len(key) if self.codes.n else 0, TOGETHER):
            k = key[i : i + TOGETHER]
            place, hit = self.codes.successor(np.zeros(len(k), np.int64), np.full(len(k), self.codes.n), k)
            out[i : i + TOGETHER][hit] = self.counts[place[hit]]
        return out


class Grams:
    """The tokens of a block and its distinct n-grams."""

    def __init__(self, s: tk.Slab, train: np.ndarray):
        """s: slab with lower-case hashes; train: flag of each document."""
        start, end = s.words()
        cuts = s.per_doc(start)
        h = s.hash(start, end)
        size = np.diff(cuts) + 1
        self.off = np.concatenate([[0], np.cumsum(size)])
        token = np.full(int(self.off[-1]), END, np.uint64)
        last = np.zeros(len(token), bool)
        last[self.off[1:] - 1] = True
        token[~last] = h
        one, two = np.full(len(token), BEGIN, np.uint64), np.full(len(token), BEGIN, np.uint64)
        one[1:], two[2:] = token[:-1], token[:-2]
        one[self.off[:-1]] = BEGIN
        two[self.off[:-1]] = BEGIN
        second = (self.off[:-1] + 1)[size > 1]
        two[second] = BEGIN
        self.context = {2: tk.mix(one ^ np.uint64(0x2545F4914F6CDD1D)), 3: tk.mix(tk.mix(two) * np.uint64(0x9FB21C651E98DF25) + one)}
        self.token, self.train = token, np.repeat(train, size)

    def distinct(self, order: int, shards: int, bits: int, hot: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(shard, key, training count, is hot, question number of each token); questions are ordered by shard and key. ``hot``: sorted codes of split contexts."""
        if order == 1:
            full = self.token
            shard = (full % np.uint64(shards)).astype(np.uint64)
            key = full >> np.uint64(20)
        else:
            c = self.context[order]
            word = self.token >> np.uint64(64 - bits)
            key = (c >> np.uint64(64 - CONTEXT_BITS)) << np.uint64(bits) | word
            shard = c % np.uint64(shards)
            split = np.isin(c, hot)
            shard[split] = tk.mix(c[split] ^ self.token[split]) % np.uint64(shards)
        by = _by_shard(np.argsort(key), shard)
        k, sh = key[by], shard[by]
        new = np.ones(len(by), bool)
        new[1:] = (k[1:] != k[:-1]) | (sh[1:] != sh[:-1])
        number = np.empty(len(by), np.int64)
        number[by] = np.cumsum(new) - 1
        count = np.bincount(number, self.train, minlength=int(new.sum())).astype(np.int64)
        head = by[new]
        is_hot = split[head] if order > 1 else np.zeros(len(head), bool)
        return shard[head].astype(np.int64), key[head], count, is_hot, number


CONTEXT_BITS = 30
SHARD_TOKENS = 2_500_000


def word_bits(tokens: int) -> dict[int, int]:
    """Bits of a word's code after one and two words. A context of two words that is not split has at most tokens / HOT_BIGRAM successors."""
    return {1: 0, 2: 28, 3: min(34, max(16, (tokens // HOT_BIGRAM).bit_length() + 4))}


def _planes(a: np.ndarray, width: int) -> bytes:
    """Integers by planes of bytes, which the compressor likes; ``width`` lowest bytes."""
    return np.ascontiguousarray(a.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def _unplanes(raw: bytes, n: int, width: int, at: int) -> np.ndarray:
    out = np.zeros((n, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n).T
    return out.view("<u8").ravel()


def _question(key: np.ndarray, count: np.ndarray, hot: np.ndarray) -> bytes:
    step = np.diff(key, prepend=np.uint64(0))
    c = np.minimum(count, 255) << 0
    more = np.flatnonzero(count >= 255)
    raw = np.int64(len(key)).tobytes() + np.int64(len(more)).tobytes() + _planes(step, 8) + c.astype(np.uint8).tobytes() + hot.astype(np.uint8).tobytes() + count[more].astype("<i8").tobytes()
    return zstandard.compress(raw, 1)


def _read_question(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw = zstandard.decompress(blob)
    n, m = np.frombuffer(raw, np.int64, 2).tolist()
    key = np.cumsum(_unplanes(raw, n, 8, 16), dtype=np.uint64)
    count = np.frombuffer(raw, np.uint8, n, 16 + 8 * n).astype(np.int64)
    hot = np.frombuffer(raw, np.uint8, n, 16 + 9 * n).astype(bool)
    count[count == 255] = np.frombuffer(raw, "<i8", m, 16 + 10 * n)
    return key, count, hot


def _ask(folder: str, shards: int, bits: dict[int, int], hot: np.ndarray, order: int):
    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        name = f"{TaskContext.get().partitionId()}.blocks"
        whole, pieces, at = zstandard.ZstdCompressor(level=3), [], 0
        for b in tk.blocks(batches, 2, BLOCK_BYTES):
            ids = b.column(0).fill_null(0).to_numpy().astype(np.int64)
            flags = np.asarray(b.column(0).is_null()).astype(np.uint8) | (np.asarray(b.column(1)).astype(np.uint8) << 1)
            for i, j, s in tk.slabs(b.column(2), lower=True, limit=2 * BLOCK_BYTES):
                raw = np.int64(j - i).tobytes() + ids[i:j].tobytes() + flags[i:j].tobytes() + s.off.astype(np.int64).tobytes() + s.data.tobytes()
                piece = whole.compress(raw)
                block = f"{name}#{at}#{len(piece)}"
                pieces.append(piece)
                at += len(piece)
                grams = Grams(s, (flags[i:j] & 3) == 0)
                names, orders, where, blobs = [block], [0], [-1 - hash_text(block) % 64], [b""]
                for n in range(1, order + 1):
                    shard, key, count, is_hot, _ = grams.distinct(n, shards, bits[n], hot)
                    cuts = np.searchsorted(shard, np.arange(shards + 1))
                    for k in np.flatnonzero(np.diff(cuts)).tolist():
                        x, y = cuts[k], cuts[k + 1]
                        names.append(block)
                        orders.append(n)
                        where.append(k)
                        blobs.append(_question(key[x:y], count[x:y], is_hot[x:y]))
                yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(np.array(orders, np.int32)), pa.array(np.array(where, np.int32)), pa.array(blobs, pa.binary())], names=["block", "n", "shard", "blob"])
        if pieces:
            shared.put(f"{folder}/{name}", b"".join(pieces))

    return run


_ANSWER = pa.schema([("block", pa.string()), ("n", pa.int32()), ("shard", pa.int32()), ("blob", pa.binary()), ("code", pa.int64()), ("total", pa.int64()), ("kinds", pa.int64())])


def _answer(folder: str, bits: dict[int, int], keep_tries: bool):
    """Rows for blocks (block, n, shard, blob) and rows of totals (no block): n = 0 for the corpus, else of split contexts."""

    @tk.tidy
    def run(table: pa.Table) -> pa.Table:
        n, shard = table["n"][0].as_py(), table["shard"][0].as_py()
        blocks = table["block"].to_pylist()
        if shard < 0:
            return _rows([(x, 0, shard, b"", None, None, None) for x in blocks])
        parts = [_read_question(x) for x in table["blob"].to_pylist()]
        key = np.concatenate([p[0] for p in parts])
        count = np.concatenate([p[1] for p in parts])
        split = np.concatenate([p[2] for p in parts])
        u, inverse = np.unique(key, return_inverse=True)
        total = np.bincount(inverse, count, minlength=len(u)).astype(np.int64)
        split_u = np.zeros(len(u), bool)
        split_u[inverse[split]] = True
        rows: list[tuple] = []
        seen = total > 0

        def through(name: str, level) -> Trie | Words:
            """The level as it is mapped from its file."""
            path = f"{folder}/{name}"
            shared.put(path, level.to_bytes())
            out = type(level).read(shared.view(path))
            if not keep_tries:
                shared.remove(path)  # the mapping holds it until the answers are there
            return out

        if n == 1:
            rows.append((None, 0, shard, b"", None, int(total.sum()), int(seen.sum())))
            c, at = through(f"1-{shard}.words", Words.build(u[seen], total[seen])).answers(u), 0
            for block, (k, _, _) in zip(blocks, parts, strict=True):
                rows.append((block, 1, shard, zstandard.compress(_planes(c[inverse[at : at + len(k)]].astype(np.uint64), 6), 1), None, None, None))
                at += len(k)
            return _rows(rows)
        width, plain = bits[n], ~split_u
        p, g = np.zeros(len(u), np.uint8), np.zeros(len(u), np.uint8)
        p[plain], g[plain] = through(f"{n}-{shard}.trie", Trie.build(u[plain & seen], total[plain & seen], width, DISCOUNT[n - 1])).answers(u[plain])
        if split_u.any():
            code = through(f"{n}-{shard}.split", Trie.build(u[split_u & seen], total[split_u & seen], width, DISCOUNT[n - 1], True)).answers(u[split_u])[0]
            p[split_u], g[split_u] = code >> 8, code & 255
        live = split_u & (total > 0)
        ctx, of = np.unique(u[live] >> np.uint64(width), return_inverse=True)
        sums, kinds = np.bincount(of, total[live], minlength=len(ctx)), np.bincount(of, minlength=len(ctx))
        rows += [(None, n, shard, b"", int(c), int(a), int(k)) for c, a, k in zip(ctx.tolist(), sums.tolist(), kinds.tolist(), strict=True)]
        at = 0
        for block, (k, _, _) in zip(blocks, parts, strict=True):
            i = inverse[at : at + len(k)]
            at += len(k)
            rows.append((block, n, shard, zstandard.compress(p[i].tobytes() + g[i].tobytes(), 1), None, None, None))
        return _rows(rows)

    return run


def _rows(rows: list[tuple]) -> pa.Table:
    return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _ANSWER, strict=True)], schema=_ANSWER) if rows else _ANSWER.empty_table()


_RESULT = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _score(folder: str, shards: int, bits: dict[int, int], hot: np.ndarray, order: int, tokens: int, kinds: int, totals: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]):
    @tk.tidy
    def run(table: pa.Table) -> pa.Table:
        block = table["block"][0].as_py()
        name, at, size = block.split("#")
        with shared.view(f"{folder}/{name}") as whole:
            raw = zstandard.ZstdDecompressor().decompress(whole[int(at) : int(at) + int(size)])
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        ids, flags = np.frombuffer(raw, np.int64, n, 8), np.frombuffer(raw, np.uint8, n, 8 + 8 * n)
        off = np.frombuffer(raw[8 + 9 * n : 16 + 17 * n], np.int64)
        grams = Grams(tk.Slab(np.frombuffer(raw, np.uint8, offset=16 + 17 * n), off, lower=True), (flags & 3) == 0)
        blobs = {(k, sh): b for k, sh, b in zip(table["n"].to_pylist(), table["shard"].to_pylist(), table["blob"].to_pylist(), strict=True) if k}
        shard, _, _, _, number = grams.distinct(1, shards, 0, hot)
        raws = [zstandard.decompress(blobs[1, k]) for k in np.unique(shard).tolist()]
        c = np.concatenate([_unplanes(x, len(x) // 6, 6, 0) for x in raws])[number].astype(float) if raws else np.empty(0)
        base = np.log10((c + 1) / (tokens + kinds + 1))
        p = np.where(c > 0, c - DISCOUNT[0], DISCOUNT[0] * max(kinds, 1)) / max(tokens, 1)
        for k in range(2, order + 1):
            shard, key, _, is_hot, number = grams.distinct(k, shards, bits[k], hot)
            raws = [zstandard.decompress(blobs[k, x]) for x in np.unique(shard).tolist()]
            a = np.concatenate([np.frombuffer(x, np.uint8, len(x) // 2) for x in raws])
            g = np.concatenate([np.frombuffer(x, np.uint8, len(x) // 2, len(x) // 2) for x in raws])
            alpha, gamma = _VALUE[a], np.where(g > 0, _VALUE[g], 1.0)
            if is_hot.any():
                code, total, kinds_of = totals.get(k, (np.empty(0, np.uint64), np.empty(0), np.empty(0)))
                ctx = key[is_hot] >> np.uint64(bits[k])
                fine = a[is_hot].astype(np.int64) << 8 | g[is_hot]
                held = np.where(fine > 0, 10.0 ** (FINE_STEP * fine - 1), 0)
                if len(code):
                    i = np.minimum(np.searchsorted(code, ctx), len(code) - 1)
                    known = code[i] == ctx
                    alpha[is_hot] = np.where(known, held / total[i], 0)
                    gamma[is_hot] = np.where(known, DISCOUNT[k - 1] * kinds_of[i] / total[i], 1.0)
                else:
                    alpha[is_hot], gamma[is_hot] = 0, 1
            p = alpha[number] + gamma[number] * p
        score = np.log10(np.minimum(p, 1.0))
        cuts = grams.off
        sums = lambda x: np.diff(np.concatenate([[0.0], np.cumsum(x)])[cuts])
        by_doc = np.repeat(np.arange(n), np.diff(cuts))
        return pa.table(
            {
                "doc_id": pa.array(ids, mask=(flags & 1).astype(bool)),
                "held_out": pa.array((flags & 2).astype(bool)),
                "n_tokens": pa.array(np.diff(cuts)),
                "n_known": pa.array(np.bincount(by_doc, c > 0, minlength=n).astype(np.int64)),
                "train_tokens": pa.array(np.full(n, tokens)),
                "base_score": pa.array(np.bincount(by_doc, base, minlength=n)),
                "score": pa.array(np.bincount(by_doc, score, minlength=n)),
            }
        )

    return run


def _frequent(order: int):
    """(n, code, count): contexts that are frequent inside a slab of training text, so a list of them is short."""

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            train = np.asarray(b.column(0)).astype(bool)
            for i, j, s in tk.slabs(b.column(1), lower=True, limit=BLOCK_BYTES):
                grams = Grams(s, train[i:j])
                t = grams.train
                size = max(int(t.sum()), 1)
                n, code, count = [0], [0], [size]
                for k, share in ((2, HOT_UNIGRAM), (3, HOT_BIGRAM)):
                    if k <= order:
                        u, c = np.unique(grams.context[k][t], return_counts=True)
                        often = c > size / share / 2
                        n += [k] * int(often.sum())
                        code += u[often].view(np.int64).tolist()
                        count += c[often].tolist()
                yield pa.RecordBatch.from_arrays([pa.array(np.array(n, np.int32)), pa.array(np.array(code, np.int64)), pa.array(np.array(count, np.int64))], names=["n", "code", "count"])

    return run


def split_contexts(rows: DataFrame, order: int) -> tuple[int, np.ndarray]:
    """Number of training tokens, and sorted codes of contexts to split: at most 2 (HOT_UNIGRAM + HOT_BIGRAM) of them."""
    got = rows.select("train", "text").mapInArrow(_frequent(order), "n int, code long, count long").groupBy("n", "code").agg(F.sum("count").alias("count"))
    got = shared.keep(got, "frequent")
    total = got.where("n = 0").agg(F.sum("count")).first()[0] or 0
    if not total:
        return 0, np.empty(0, np.uint64)
    share = F.when(F.col("n") == 2, HOT_UNIGRAM).otherwise(HOT_BIGRAM)
    hot = got.where((F.col("n") > 0) & (F.col("count") * share * 2 > total)).select("code").collect()
    return int(total), np.sort(np.array([r["code"] for r in hot], np.int64).view(np.uint64))


def score(docs: DataFrame, held_out: Column, order: int = ORDER, text: str = "text", keep_tries: bool = False) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score. Learns from rows whose ``held_out`` is false and whose doc_id is not null."""
    spark = docs.sparkSession
    docs = shared.settled(docs)
    folder, tries = shared.fresh(spark, "blocks"), shared.fresh(spark, "tries")
    ident = docs["doc_id"].cast("long")
    rows = docs.select(ident.alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held"), (~F.coalesce(held_out, F.lit(False)) & ident.isNotNull()).alias("train"), docs[text].cast("string").alias("text"))
    expected, hot = split_contexts(rows, order)
    shards, bits = max(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), -(-expected // SHARD_TOKENS)), word_bits(expected)
    asked = rows.select("doc_id", "held", "text").mapInArrow(_ask(folder, shards, bits, hot, order), "block string, n int, shard int, blob binary")
    answers = shared.keep(asked.groupBy("n", "shard").applyInArrow(_answer(tries, bits, keep_tries), "block string, n int, shard int, blob binary, code long, total long, kinds long"), "answers")
    tokens, kinds, totals = 0, 0, {}
    sums = answers.where("block is null").groupBy("n", "code").agg(F.sum("total").alias("total"), F.sum("kinds").alias("kinds")).collect()  # one row, and one for each split context
    for r in sums:
        if r["n"] == 0:
            tokens, kinds = r["total"] or 0, r["kinds"] or 0
    for k in range(2, order + 1):
        some = sorted((r["code"], r["total"], r["kinds"]) for r in sums if r["n"] == k)
        totals[k] = tuple(np.array([x[i] for x in some], t) for i, t in enumerate((np.uint64, float, float)))
    return answers.where("block is not null").select("block", "n", "shard", "blob").groupBy("block").applyInArrow(_score(folder, shards, bits, hot, order, tokens, kinds, totals), _RESULT)
