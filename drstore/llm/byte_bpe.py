"""Byte-level BPE by longest matches with backtracking.

A rank file (``tiktoken`` format) lists tokens; the merge of two tokens has the rank of the token they form.
Every vocabulary byte string is mapped to Latin-1 text and put into an Aho-Corasick automaton, so
one call gives the longest token that begins at a position. A piece is encoded left to right:
take the longest token, keep it if the pair (previous token, token) is *compatible* - the merge
procedure applied to their concatenation would give back just these two - and else
fall back to the next shorter token, or undo the previous one. An encoding all of whose adjacent pairs
are compatible is the one that the merges give, and there is exactly one. Dead positions are remembered, so
each position is left for good at most once and the work is linear in the piece.

Pairs are judged by merging their bytes and are memoised; whole pieces are memoised
too, in tables of bounded size. Decoding concatenates token bytes.

Null text is empty text and gives no ids. Rows are independent: repeated rows give repeated results, an empty
table an empty one; other columns are ignored unless ``carry`` names them.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import textkit as tk

#: Bounds of the memo tables of one worker: pieces (and the characters of a piece that is kept), pairs.
MEMO_ENTRIES, MEMO_PIECE, MEMO_PAIRS = 300_000, 64, 300_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class ByteBPE:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import ahocorasick

        self.ranks, self.pattern = ranks, regex.compile(pattern)
        self.token = {r: t for t, r in ranks.items()}
        self.automaton = ahocorasick.Automaton()
        for t, r in ranks.items():
            self.automaton.add_word(t.decode("latin-1"), (r, len(t)))
        self.automaton.make_automaton()
        self._fits: dict[int, bool] = {}
        self._shorter: dict[int, int] = {}
        self._memo: dict[str, tuple[int, ...]] = {}

    def _merge(self, piece: bytes) -> list[int]:
        """The defining procedure: again and again merge the leftmost pair of least rank."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                r = self.ranks.get(parts[i] + parts[i + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, i
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [self.ranks[p] for p in parts]

    def fits(self, a: int, b: int) -> bool:
        """Whether tokens a, b side by side survive the merges as they are."""
        key = a << 24 | b
        known = self._fits.get(key)
        if known is None:
            if len(self._fits) >= MEMO_PAIRS:
                self._fits.clear()
            known = self._fits[key] = self._merge(self.token[a] + self.token[b]) == [a, b]
        return known

    def shorter(self, r: int) -> int:
        """The longest token that is a proper prefix of token r, -1 if there is none."""
        found = self._shorter.get(r)
        if found is None:
            t, found = self.token[r], -1
            for n in range(len(t) - 1, 0, -1):
                if (k := self.ranks.get(t[:n])) is not None:
                    found = k
                    break
            self._shorter[r] = found
        return found

    def piece(self, data: bytes) -> tuple[int, ...]:
        """Ids of one pre-split piece."""
        if (r := self.ranks.get(data)) is not None:
            return (r,)
        n = len(data)
        longest = [-1] * n
        for end, (r, k) in self.automaton.iter(data.decode("latin-1")):
            longest[end + 1 - k] = r  # ends only grow, so the longest is the last
        dead = bytearray(n + 1)
        path: list[int] = []
        at, r, token, fits = 0, longest[0], self.token, self.fits
        while at < n:
            placed = False
            while r >= 0:
                to = at + len(token[r])
                if not dead[to] and (not path or fits(path[-1], r)):
                    path.append(r)
                    at, placed = to, True
                    r = longest[at] if at < n else -1
                    break
                r = self.shorter(r)
            if not placed:
                if not path:
                    raise ValueError("the vocabulary lacks a byte of the text")
                dead[at] = 1
                last = path.pop()
                at -= len(token[last])
                r = self.shorter(last)
        return tuple(path)

    def ids(self, text: str) -> list[int]:
        out: list[int] = []
        memo, extend = self._memo, out.extend
        for p in self.pattern.findall(text):
            got = memo.get(p)
            if got is None:
                got = self.piece(p.encode("utf-8"))
                if len(p) <= MEMO_PIECE:
                    if len(memo) >= MEMO_ENTRIES:
                        memo.clear()
                    memo[p] = got
            extend(got)
        return out

    def forget(self) -> None:
        """Empty the memo of pieces."""
        self._memo.clear()

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.token.__getitem__, ids))


_models: dict[tuple[str, str], ByteBPE] = {}


def model(path: str, pattern: str) -> ByteBPE:
    """One model for each worker process."""
    if (path, pattern) not in _models:
        _models[path, pattern] = ByteBPE(read_ranks(path), pattern)
    return _models[path, pattern]


def _encoder(path: str, pattern: str, ids: bool, check: bool, carry: int):
    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(path, pattern)
        for b in batches:
            n_tokens, lists, ids_sha, decoded_sha = [], [], [], []
            for t in b.column(carry).to_pylist():
                got = m.ids(t or "")
                packed = np.array(got, "<u4").tobytes()
                n_tokens.append(len(got))
                if ids:
                    lists.append(packed)
                else:
                    ids_sha.append(hashlib.sha256(packed).hexdigest())
                if check:
                    decoded_sha.append(hashlib.sha256(m.decode(got)).hexdigest())
            extra = {"ids_le32": pa.array(lists, pa.binary())} if ids else {"ids_sha256": pa.array(ids_sha, pa.string())}
            if check:
                extra["decoded_sha256"] = pa.array(decoded_sha, pa.string())
            yield pa.RecordBatch.from_arrays([*b.columns[:carry], pa.array(n_tokens, pa.int64()), *extra.values()], names=[*b.schema.names[:carry], "n_tokens", *extra])
        m.forget()  # workers live on; their next task may be another operator's

    return run


def encode(docs: DataFrame, path: str, pattern: str, text: str = "text", carry: Sequence[str] = ("doc_id",), check: bool = False) -> DataFrame:
    """``carry`` columns, n_tokens LONG, ids_le32 BINARY (little-endian unsigned 32-bit ids) and, if ``check``, decoded_sha256 of the bytes they decode to."""
    src = docs.select(*carry, docs[text].cast("string").alias("__text"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema[:-1]) + ", n_tokens long, ids_le32 binary" + (", decoded_sha256 string" if check else "")
    return src.mapInArrow(_encoder(path, pattern, True, check, len(carry)), schema)


def digests(docs: DataFrame, path: str, pattern: str, text: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: encodes every text and decodes the ids again."""
    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs[text].cast("string").alias("__text"))
    return src.mapInArrow(_encoder(path, pattern, False, True, 1), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """Adds text STRING to rows with ids_le32."""
    names = encoded.columns
    at = names.index("ids_le32")

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(path, pattern)
        for b in batches:
            out = [m.decode(np.frombuffer(x or b"", "<u4").tolist()).decode("utf-8") for x in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.string())], names=[*b.schema.names, "decoded_text"])

    return encoded.mapInArrow(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in encoded.schema) + ", decoded_text string")
