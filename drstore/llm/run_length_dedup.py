"""Removal of long byte strings that an earlier document holds, by run-length indexes over the repeated parts of a corpus.

A byte goes if a ``REACH``-byte string over it also starts in a document with a smaller doc_id. The corpus is reduced first, without loss:
every ``REACH``-byte string holds an *anchor*, the ``GRAM``-byte string in it whose hash is least (the leftmost of equals), so equal strings have equal anchors
in equal places. Only anchors that occur in two documents or more can matter.

1. Tasks copy their documents to block files in the shared folder and send the distinct anchor hashes of each block, packed, to shards of hashes,
   which find those that two documents share.
2. Each block cuts the *snippet* around every shared anchor: all ``REACH``-byte strings that contain it. Equal snippets of a block are combined and sent by
   anchor, with the least and greatest doc_id.
3. A shard keeps anchors together. A snippet's owner is its least doc_id; in any other document all of it goes. Snippets of an anchor that agree far enough
   beyond it on a side are put, by owner, into a run-length index and matching statistics of each against the smaller owners mark further strings.
4. The verdicts return to the blocks, which rebuild their documents.

An anchor whose snippets differ inside ``HOT_BLOCKS`` slabs or more may have one for every document. Its strings are sent one by one instead, by their own hash, so equal ones are
combined in each block and no shard gathers an anchor's documents.

Null text is empty text. Null doc_id counts as smaller than any; rows with equal doc_id do not touch each other. An empty table gives an empty
result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared
from . import textkit as tk
from .run_length_index import RunLengthIndex

REACH, GRAM = 50, 32
WINDOW = REACH - GRAM + 1  # grams in a string, and strings around an anchor
WIDTH = 2 * REACH - GRAM
HOT_BLOCKS = 1000
BLOCK_BYTES = 1 << 21
MOST_TOGETHER = 8
INDEXED = 2048
NULL_ID = -(1 << 63)


def anchors(s: tk.Slab) -> tuple[np.ndarray, np.ndarray]:
    """(positions, 40-bit hashes) of the anchors of a slab."""
    n = len(s.data) - GRAM + 1
    if n < WINDOW:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    code = s.gram_hashes(GRAM) >> np.uint64(24)
    size = np.diff(s.off)
    inside = np.repeat(np.tile([True, False], s.n), np.column_stack([np.maximum(size - REACH + 1, 0), np.minimum(size, REACH - 1)]).ravel())
    found = []
    for low in range(0, n - WINDOW + 1, _PIECE):  # strings that begin in low.. ; places are 24 bits beside the 40 of a hash
        part = code[low : low + _PIECE + WINDOW - 1]
        span, step = part << np.uint64(24) | np.arange(len(part), dtype=np.uint64), 1
        while 2 * step <= WINDOW:  # least of WINDOW neighbours, by doubling
            span = np.minimum(span[:-step], span[step:])
            step *= 2
        if WINDOW > step:
            span = np.minimum(span[: step - WINDOW], span[WINDOW - step :])
        place = (span & np.uint64(0xFFFFFF)).astype(np.int32)[inside[low : low + len(span)]]
        found.append(low + place[_fresh(place)].astype(np.int64))
    position = np.concatenate(found)  # ascending, for the leftmost least of a window is never left of the one before
    position = position[_fresh(position)]
    return position, code[position]


_PIECE = 1 << 17


def _fresh(x: np.ndarray) -> np.ndarray:
    """Flag of each entry that differs from the one before."""
    out = np.ones(len(x), bool)
    out[1:] = x[1:] != x[:-1]
    return out


def _combined(key: np.ndarray, *columns: tuple[np.ufunc, np.ndarray]) -> tuple[np.ndarray, ...]:
    """(an entry of each distinct key in ascending order, the key's number of entries, each column reduced over them)."""
    order = np.argsort(key)
    first = np.flatnonzero(_fresh(key[order]))
    if not len(first):
        return order, first, *(x for _, x in columns)
    return order[first], np.diff(first, append=len(order)), *(f.reduceat(x[order], first) for f, x in columns)


def _distinct(s: tk.Slab, ids: np.ndarray, position: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(code, least and greatest doc_id, whether it has snippets that differ) of each distinct anchor hash of a slab."""
    owner = ids[s.doc_of(position)] if len(position) else np.empty(0, np.int64)
    one, count, least, most = _combined(code, (np.minimum, owner), (np.maximum, owner))
    apart = np.zeros(len(one), bool)
    if (count > 1).any():
        of = np.searchsorted(code[one], code)
        again = np.flatnonzero(count[of] > 1)
        of, at = of[again], position[again]
        sid = _snippet_ids(s, at, *_snippet_bounds(s, at))
        some = np.empty(len(one), np.uint64)
        some[of] = sid  # one of them
        apart[of[some[of] != sid]] = True
    return code[one], least, most, apart


def _shard(code: np.ndarray, shards: int) -> np.ndarray:
    return (code % np.uint64(shards)).astype(np.int64)


def _store(folder: str, shards: int, block_bytes: int, together: int):
    """Rows (block, shard, codes): distinct 40-bit anchor hashes, flagged if two documents of the block share them, if a slab has snippets of them that differ, and if half of its slabs have them.

    A block is a file of ``together`` slabs of about ``block_bytes``, each with the places of its anchors.
    """

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, number, whole = TaskContext.get().partitionId(), 0, zstandard.ZstdCompressor(level=1)
        pieces, held = [], []
        for b in tk.blocks(batches, 1, block_bytes):
            ids = b.column(0).fill_null(NULL_ID).to_numpy().astype(np.int64)
            null = np.asarray(b.column(0).is_null())
            for i, j, s in tk.slabs(b.column(1), limit=2 * block_bytes):
                position, code = anchors(s)
                steps = _steps(position)
                raw = np.array([j - i, len(steps)]).tobytes() + ids[i:j].tobytes() + s.off.astype(np.int64).tobytes() + null[i:j].astype(np.uint8).tobytes() + steps.tobytes() + s.data.tobytes()
                pieces.append(whole.compress(raw))
                held.append(_distinct(s, ids[i:j], position, code))
                if len(pieces) == together:
                    yield _sent(folder, f"{task}-{number}.blocks", shards, pieces, held)
                    pieces, held, number = [], [], number + 1
        if pieces:
            yield _sent(folder, f"{task}-{number}.blocks", shards, pieces, held)

    return run


def _sent(folder: str, block: str, shards: int, pieces: list[bytes], held: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
    """Write a block; its rows by shard."""
    shared.put(f"{folder}/{block}", np.array([len(pieces), *map(len, pieces)]).tobytes() + b"".join(pieces))
    code, least, most, apart = (np.concatenate(x) for x in zip(*held, strict=True))
    often = np.ones(len(code), bool)
    if len(held) > 1:
        one, slabs, least, most, apart = _combined(code, (np.minimum, least), (np.maximum, most), (np.logical_or, apart))
        code, often = code[one], 2 * slabs >= len(held)
    twice, shard = least != most, _shard(code, shards)
    order = _by_shard(np.arange(len(code)), shard)
    code, twice, apart, often, shard = code[order], twice[order], apart[order], often[order], shard[order]
    cuts = np.searchsorted(shard, np.arange(shards + 1))
    code = _inside(code, shards)
    blobs = [_pack(code[x:y], twice[x:y], apart[x:y], often[x:y]) for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True) if y > x]
    live = np.flatnonzero(np.diff(cuts))
    return pa.RecordBatch.from_arrays([pa.array([block] * (len(blobs) + 1)), pa.array(np.append(live, -1 - hash_text(block) % 64).astype(np.int32)), pa.array([*blobs, b""], pa.binary())], names=["block", "shard", "codes"])


def _steps(position: np.ndarray) -> np.ndarray:
    """Ascending places as bytes: each step beyond the place before, 255 standing for that many and more to come."""
    step = np.diff(position, prepend=0)
    end = np.cumsum(step // 255 + 1)
    out = np.full(int(end[-1]) if len(end) else 0, 255, np.uint8)
    out[end - 1] = step % 255
    return out


def _places(steps: np.ndarray) -> np.ndarray:
    return np.cumsum(steps, dtype=np.int64)[steps != 255]


def hash_text(x: str) -> int:
    return int.from_bytes(hashlib.blake2b(x.encode(), digest_size=6).digest(), "little")


def _pack(code: np.ndarray, *flags: np.ndarray) -> bytes:
    """4 bytes each: 29 bits of a code and up to three flags."""
    out = code.astype(np.uint32) << np.uint32(3)
    for k, flag in enumerate(flags):
        out |= flag.astype(np.uint32) << np.uint32(k)
    return out.tobytes()


def _unpack(blob: bytes) -> tuple[np.ndarray, ...]:
    v = np.frombuffer(blob, np.uint32)
    return v >> np.uint32(3), *((v & np.uint32(1 << k)).astype(bool) for k in range(3))


def _by_shard(order: np.ndarray, shard: np.ndarray) -> np.ndarray:
    """An order, regrouped by shard."""
    return order[np.argsort(shard[order].astype(np.uint16) if shard.max(initial=0) < 1 << 16 else shard[order], kind="stable")]


def _inside(code: np.ndarray, shards: int) -> np.ndarray:
    """29 bits that tell codes of one shard apart (all but one in some thousands; a mistake costs work, not results)."""
    return (code // np.uint64(shards)) & np.uint64((1 << 29) - 1)


@tk.tidy
def _shared_codes(table: pa.Table, hot_slabs: int, together: int) -> pa.Table:
    """(block, codes): for each block of a shard the codes that two documents share, flagged if hot (a block where its snippets differ counts for all its slabs if half of them have the code, else for one); rows of a negative shard pass, so every block is known."""
    blocks, blobs = table["block"].to_pylist(), table["codes"].to_pylist()
    if table.num_rows and table["shard"][0].as_py() < 0:
        return pa.table({"block": pa.array(blocks, pa.string()), "shard": table["shard"], "codes": pa.array([b""] * len(blocks), pa.binary())})
    shard = table["shard"][0].as_py()
    parts = [_unpack(x) for x in blobs]
    code = np.concatenate([p[0] for p in parts])
    flag = np.concatenate([p[1] for p in parts])
    apart, often = (np.concatenate([p[k] for p in parts]) for k in (2, 3))
    u, inverse, n = np.unique(code, return_inverse=True, return_counts=True)
    within = np.zeros(len(u), bool)
    within[inverse[flag]] = True
    # two blocks may hold rows of one doc_id only; that costs work, not results
    wanted, hot = within | (n >= 2), np.bincount(inverse[apart], np.where(often, together, 1)[apart], minlength=len(u)) >= hot_slabs
    out_block, out_codes, at = [], [], 0
    for name, (c, *_) in zip(blocks, parts, strict=True):
        i = inverse[at : at + len(c)]
        at += len(c)
        keep = wanted[i]
        if keep.any():
            out_block.append(name)
            out_codes.append(_pack(c[keep], hot[i][keep]))
    return pa.table({"block": pa.array(out_block, pa.string()), "shard": pa.array([shard] * len(out_block), pa.int32()), "codes": pa.array(out_codes, pa.binary())})


def _open(folder: str, block: str) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, tk.Slab]]:
    """(doc ids, null flags, places of anchors, slab) of each slab of a block."""
    with shared.view(f"{folder}/{block}") as whole:
        count = int(np.frombuffer(whole, np.int64, 1)[0])
        sizes = np.frombuffer(whole[8 : 8 + 8 * count], np.int64).tolist()
        at = 8 + 8 * count
        for size in sizes:
            raw = zstandard.ZstdDecompressor().decompress(whole[at : at + size])
            at += size
            n, steps = np.frombuffer(raw, np.int64, 2).tolist()
            ids, off = np.frombuffer(raw, np.int64, n, 16), np.frombuffer(raw, np.int64, n + 1, 16 + 8 * n)
            flags = 24 + 16 * n
            null = np.frombuffer(raw, np.uint8, n, flags).astype(bool)
            yield ids, null, _places(np.frombuffer(raw, np.uint8, steps, flags + n)), tk.Slab(np.frombuffer(raw, np.uint8, offset=flags + n + steps), off)


def _snippet_bounds(s: tk.Slab, position: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    doc = s.doc_of(position)
    return np.maximum(position - (REACH - GRAM), s.off[doc]), np.minimum(position + REACH, s.off[doc + 1])


def _snippet_ids(s: tk.Slab, position: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    return tk.mix(s.hash(begin, end) + (position - begin).astype(np.uint64) * np.uint64(0x9E6C63D0876A9A47)) & ~np.uint64(1)


def _flat_ids(hashes: np.ndarray) -> np.ndarray:
    """Identities of single strings, of their hashes; they are odd and those of snippets even."""
    return tk.mix(hashes ^ np.uint64(0x632BE59BD9B4E019)) | np.uint64(1)


def _snippets(folder: str, shards: int):
    """Rows (shard, block, blob): for each distinct snippet of a block the anchor's place in it, its bytes, least and greatest doc_id."""

    @tk.tidy
    def run(table: pa.Table) -> pa.Table:
        block = table["block"][0].as_py()
        parts = [(k, *_unpack(x)) for k, x in zip(table["shard"].to_pylist(), table["codes"].to_pylist(), strict=True) if x]
        if not parts:
            return pa.table({"shard": pa.array([], pa.int32()), "block": pa.array([], pa.string()), "blob": pa.array([], pa.binary())})
        wanted = np.concatenate([np.uint64(k << 29) | c.astype(np.uint64) for k, c, *_ in parts])
        hot = np.concatenate([p[2] for p in parts])
        order = np.argsort(wanted)
        wanted, hot = wanted[order], hot[order]
        texts, found, at = [], [], 0
        for ids, _, position, s in _open(folder, block):
            texts.append(s.data)
            if len(position):
                found.append(_cut(s, ids, position, wanted, hot, shards, at))
            at += len(s.data)
        key, sid, place, begin, size, least, most = (np.concatenate(x) for x in zip(*found, strict=True))
        if len(found) > 1:
            one, _, least, most = _combined(sid, (np.minimum, least), (np.maximum, most))
            key, place, begin, size = key[one], place[one], begin[one], size[one]
        end, shard = begin + size, _shard(key, shards)
        order = _by_shard(np.argsort(begin), shard)  # neighbours share bytes
        shard, place, begin, end, least, most = (x[order] for x in (shard, place, begin, end, least, most))
        flat = np.concatenate(texts)
        cuts = np.searchsorted(shard, np.arange(shards + 1))
        rows, blobs = np.flatnonzero(np.diff(cuts)), []
        for r in rows.tolist():
            x, y = cuts[r], cuts[r + 1]
            size = end[x:y] - begin[x:y]
            at = np.repeat(begin[x:y] - np.cumsum(size) + size, size) + np.arange(int(size.sum()))
            blobs.append(zstandard.compress(np.int64(y - x).tobytes() + least[x:y].tobytes() + (most[x:y] - least[x:y]).tobytes() + size.astype(np.uint8).tobytes() + place[x:y].astype(np.uint8).tobytes() + flat[at].tobytes(), 1))
        return pa.table({"shard": pa.array(rows.astype(np.int32)), "block": pa.array([block] * len(rows), pa.string()), "blob": pa.array(blobs, pa.binary())})

    return run


def _cut(s: tk.Slab, ids: np.ndarray, position: np.ndarray, wanted: np.ndarray, hot: np.ndarray, shards: int, at: int) -> tuple[np.ndarray, ...]:
    """(key, identity, anchor's place, begin in the block, size, least and greatest doc_id) of each distinct snippet or single string of a slab that begins at ``at``."""
    code = s.hash(position, position + GRAM) >> np.uint64(24)
    low = (code % np.uint64(shards)) << np.uint64(29) | _inside(code, shards)
    i = np.minimum(np.searchsorted(wanted, low), len(wanted) - 1)
    hit = wanted[i] == low
    position, code, is_hot = position[hit], code[hit], hot[i[hit]]
    begin, end = _snippet_bounds(s, position)
    key, sid, place = code, _snippet_ids(s, position, begin, end), position - begin
    if is_hot.any():
        # single strings in place of the snippets of hot anchors
        b, e = begin[is_hot], end[is_hot]
        count = e - b - REACH + 1
        single = np.repeat(b, count) + np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
        one = _flat_ids(s.hash(single, single + REACH))
        begin, end = np.concatenate([begin[~is_hot], single]), np.concatenate([end[~is_hot], single + REACH])
        key, sid, place = np.concatenate([key[~is_hot], one]), np.concatenate([sid[~is_hot], one]), np.concatenate([place[~is_hot], np.full(len(one), 255)])
    owner = ids[s.doc_of(begin)] if len(begin) else np.empty(0, np.int64)
    one, _, least, most = _combined(sid, (np.minimum, owner), (np.maximum, owner))
    return key[one], sid[one], place[one].astype(np.uint8), at + begin[one], (end - begin)[one].astype(np.uint8), least, most


ELSEWHERE = np.uint32(1 << 31)
HALF = (REACH - GRAM + 1) // 2


def _twice(h: np.ndarray) -> np.ndarray:
    """Places whose value occurs more than once."""
    order = np.argsort(h)
    same = h[order][1:] == h[order][:-1]
    out = np.zeros(len(h), bool)
    out[order[1:][same]] = True
    out[order[:-1][same]] = True
    return np.flatnonzero(out)


def _groups(anchor: np.ndarray) -> Iterator[np.ndarray]:
    """Entries in groups of about ``INDEXED``; those of an anchor stay together, for only they can share strings that it decides."""
    order = np.argsort(anchor)
    start = np.flatnonzero(_fresh(anchor[order]))
    while len(start):
        low = start[0]
        k = int(np.searchsorted(start, low + INDEXED, side="right"))  # the first anchor that begins beyond
        high = start[k] if k < len(start) else len(order)
        yield order[low:high]
        start = start[k:]


@tk.tidy
def _verdicts(table: pa.Table) -> pa.Table:
    """Rows (block, blob): for each snippet of a block that loses bytes its identity and the strings that go in the least document, or that all goes."""
    blocks = table["block"].to_pylist()
    least, more, length, place, data, of = [], [], [], [], [], []
    for k, blob in enumerate(table["blob"].to_pylist()):
        raw = zstandard.decompress(blob)
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        least.append(np.frombuffer(raw, np.int64, n, 8))
        more.append(np.frombuffer(raw, np.int64, n, 8 + 8 * n))
        length.append(np.frombuffer(raw, np.uint8, n, 8 + 16 * n).astype(np.int64))
        place.append(np.frombuffer(raw, np.uint8, n, 8 + 17 * n).astype(np.int64))
        data.append(np.frombuffer(raw, np.uint8, offset=8 + 18 * n))
        of.append(np.full(n, k))
    least, more, length, place, of = (np.concatenate(x) for x in (least, more, length, place, of))
    begin = np.concatenate([[0], np.cumsum(length)])
    s = tk.Slab(np.concatenate(data), np.array([0, begin[-1]]))
    begin, end = begin[:-1], begin[1:]
    single = place == 255
    position = begin + np.where(single, 0, place)
    sid = _snippet_ids(s, position, begin, end)
    if single.any():
        sid[single] = _flat_ids(s.hash(begin[single], end[single]))
    # one entry for each identity
    order = np.argsort(sid)
    ranked = sid[order]
    first = np.concatenate([[True], ranked[1:] != ranked[:-1]])
    head = order[first]
    entry = np.empty(len(order), np.int64)
    entry[order] = np.cumsum(first) - 1
    owner = np.minimum.reduceat(least[order], np.flatnonzero(first))
    mask = np.zeros(len(head), np.uint32)
    # strings that two snippets of an anchor share reach HALF bytes or more beyond it on one side
    h = np.flatnonzero(~single[head])
    at, near = position[head[h]], np.zeros(len(head), bool)
    for fits, first_byte, last_byte in ((place[head[h]] >= HALF, at - HALF, at + GRAM), (length[head[h]] - place[head[h]] - GRAM >= HALF, at, at + GRAM + HALF)):
        near[h[fits][_twice(s.hash(first_byte[fits], last_byte[fits]))]] = True
    contested = np.flatnonzero(near)
    for group in _groups(s.hash(position[head[contested]], position[head[contested]] + GRAM)):
        by = contested[group]
        by = by[np.argsort(owner[by], kind="stable")]
        rows = head[by]
        column = np.arange(WIDTH)
        inside = column[None, :] < length[rows][:, None]
        symbols = np.zeros((len(rows), WIDTH), np.uint16)
        symbols[inside] = s.data[(begin[rows][:, None] + column[None, :])[inside]].astype(np.uint16) + np.uint16(1)
        index = RunLengthIndex(symbols, length[rows], owner[by], REACH)
        found = index.earlier(owner[by])[:, :WINDOW]
        mask[by] = (found.astype(np.uint32) << np.arange(WINDOW, dtype=np.uint32)).sum(1, dtype=np.uint32)
    told = np.where(owner[entry] < least, ELSEWHERE, mask[entry])
    tells = (told > 0) | (more > 0)
    out = []
    cuts = np.searchsorted(of, np.arange(len(blocks) + 1))
    for k in range(len(blocks)):
        t = np.arange(cuts[k], cuts[k + 1])[tells[cuts[k] : cuts[k + 1]]]
        out.append(zstandard.compress(sid[t].tobytes() + told[t].tobytes(), 1) if len(t) else b"")
    keep = [k for k, x in enumerate(out) if x]
    return pa.table({"block": pa.array([blocks[k] for k in keep], pa.string()), "blob": pa.array([out[k] for k in keep], pa.binary())})


class Verdicts:
    """What the shards say of a block: identities and their verdicts. Every slab is looked up before one is judged, for the least owner of an identity may be in a later slab."""

    def __init__(self, sid: np.ndarray, told: np.ndarray):
        order = np.argsort(sid)
        self.sid, self.told = sid[order], told[order]
        self.least = np.full(len(sid), np.iinfo(np.int64).max)
        odd = self.sid[(self.sid & np.uint64(1)).astype(bool)]
        self.single = None
        if len(odd):  # most places hold no string of a hot anchor, as few bits of its hash tell
            self.single = np.zeros(1 << 22, bool)
            self.single[odd >> np.uint64(42)] = True

    def look(self, s: tk.Slab, ids: np.ndarray, position: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(identities, begins, ends, owners) of what a slab holds of them."""
        begin, end = _snippet_bounds(s, position)
        found = [self._known(ids, s, _snippet_ids(s, position, begin, end), begin, end)]
        if self.single is not None:
            one = _flat_ids(s.gram_hashes(REACH))
            at = np.flatnonzero(self.single[one >> np.uint64(42)])
            at = at[at + REACH <= s.off[s.doc_of(at) + 1]]
            found.append(self._known(ids, s, one[at], at, at + REACH))
        return found

    def _known(self, ids: np.ndarray, s: tk.Slab, sid: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        i = np.minimum(np.searchsorted(self.sid, sid), len(self.sid) - 1)
        hit = self.sid[i] == sid
        i, begin, end = i[hit], begin[hit], end[hit]
        owner = ids[s.doc_of(begin)] if len(begin) else np.empty(0, np.int64)
        np.minimum.at(self.least, i, owner)
        return i, begin, end, owner

    def gone(self, n: int, found: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]) -> np.ndarray:
        """Flag of each of n bytes of a slab that goes."""
        change = np.zeros(n + 1, np.int64)
        for i, begin, end, owner in found:
            told = self.told[i]
            whole = (told == ELSEWHERE) | (owner > self.least[i])
            begins, ends = [begin[whole]], [end[whole]]
            begin, mask = begin[~whole], told[~whole]
            begin, mask = begin[mask > 0], mask[mask > 0]
            for k in range(WINDOW):
                at = begin[((mask >> np.uint32(k)) & np.uint32(1)).astype(bool)] + k
                begins.append(at)
                ends.append(at + REACH)
            change += np.bincount(np.concatenate(begins), minlength=n + 1) - np.bincount(np.concatenate(ends), minlength=n + 1)
        return np.cumsum(change)[:-1] > 0


_SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())])


def _rebuild(folder: str, full: bool):
    @tk.tidy
    def run(table: pa.Table) -> pa.Table:
        block = table["block"][0].as_py()
        slabs = list(_open(folder, block))
        raws = [zstandard.decompress(x) for x in table["blob"].to_pylist() if x]
        verdicts, found = None, []
        if raws:
            verdicts = Verdicts(np.concatenate([np.frombuffer(x, np.uint64, len(x) // 12) for x in raws]), np.concatenate([np.frombuffer(x, np.uint32, offset=len(x) // 12 * 8) for x in raws]))
            for ids, _, position, s in slabs:
                found.append(verdicts.look(s, ids, position) if len(position) else [])
                s.forget()
        return pa.concat_tables(_rows(s, ids, null, verdicts.gone(len(s.data), found[k]) if verdicts else np.zeros(len(s.data), bool), full) for k, (ids, null, _, s) in enumerate(slabs))

    return run


def _rows(s: tk.Slab, ids: np.ndarray, null: np.ndarray, gone: np.ndarray, full: bool) -> pa.Table:
    """The result's rows of a slab."""
    begin = gone.copy()
    begin[1:] &= ~gone[:-1]
    starts = s.off[:-1][s.off[:-1] < s.off[1:]]
    begin[starts] = gone[starts]
    size, lost, spans = np.diff(s.off), s.sums_by_doc(gone), s.sums_by_doc(begin)
    kept = []
    for d in range(s.n):
        part = s.data[s.off[d] : s.off[d + 1]]
        kept.append((part[~gone[s.off[d] : s.off[d + 1]]] if lost[d] else part).tobytes())
    out = {"doc_id": pa.array(ids, mask=null), "n_bytes": pa.array(size), "n_removed": pa.array(lost), "n_spans": pa.array(spans), "kept_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in kept])}
    if full:
        out["kept"] = pa.array(kept, pa.binary())
    return pa.table(out)


def deduplicate(docs: DataFrame, text: str = "text", full: bool = False, hot_blocks: int = HOT_BLOCKS, block_bytes: int = BLOCK_BYTES, together: int | None = None) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if ``full``, the remaining bytes.

    ``together``: slabs of a block; as many as the shards ask for by default, since every block sends each shard a row.
    """
    spark = docs.sparkSession
    docs = shared.settled(docs)
    folder = shared.fresh(spark, "blocks")
    shards = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs[text].cast("string").alias("text"))
    slabs = together or min(MOST_TOGETHER, max(1, shards // 64))
    sent = src.mapInArrow(_store(folder, shards, block_bytes, slabs), "block string, shard int, codes binary")
    marks = shared.keep(sent.groupBy("shard").applyInArrow(lambda t: _shared_codes(t, hot_blocks, slabs), "block string, shard int, codes binary"), "marks")
    cut = marks.groupBy("block").applyInArrow(_snippets(folder, shards), "shard int, block string, blob binary")
    told = cut.groupBy("shard").applyInArrow(_verdicts, "block string, blob binary")
    known = marks.where("octet_length(codes) = 0").select("block", F.lit(None).cast("binary").alias("blob"))
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if full else "")
    return told.unionByName(known).groupBy("block").applyInArrow(_rebuild(folder, full), schema)
