"""Factors of many documents at once.

Eight bytes are compared at a time as one big-endian integer. The greedy factors are a walk over the text. Walks from every document's first byte and from
every ``STRIDE``-th place of a window take their steps together, so how far a match goes, up to ``DEEP`` bytes, is found for many places at once: they are sorted
by their next eight bytes, looked up among the sorted first eight bytes of the suffixes, and those that match all eight go on inside their interval by binary
searches on the next eight. A walk ends where another has been. A place whose match is longer still is searched alone.
Ranks are looked up for the places of that walk only.

Documents stand one after another and no match goes beyond its document, so the walk over a window meets every document's first byte.

An integer is padded with zeros where fewer than eight bytes are left, so a string and the same string with zero bytes after it look alike; the shorter one is
the smaller suffix, and ``_settle`` passes over suffixes that end too early.
"""

from __future__ import annotations

import numpy as np

from .suffix import LEAST, Searcher

DEEP = 64
WINDOW = 1 << 23
STRIDE = 256
_MASK = np.array([0, *(((1 << (8 * k)) - 1) << (64 - 8 * k) for k in range(1, 9))], np.uint64)
_STEPS = [np.uint64(1 << (8 * k)) for k in range(7, 0, -1)]


class Ahead:
    """At places of a text the next eight bytes as integers, zeros beyond the end. They are made from the bytes when asked for."""

    def __init__(self, a: np.ndarray):
        wide = np.zeros(len(a) + 17, np.uint8)
        wide[: len(a)] = a
        self.view = np.ndarray((len(a) + 9,), ">u8", wide, strides=(1,))

    def __getitem__(self, at: np.ndarray) -> np.ndarray:
        return self.view[at].astype(np.uint64)


def _equal_bytes(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = a ^ b
    n = (x == 0).astype(np.int64)
    for s in _STEPS:
        n += x < s
    return n


class Bulk:
    def __init__(self, search: Searcher, tie: str = "first_rank"):
        self.search, self.m, self.tie = search, search.m, tie
        self.sa, self.keys, self.view = np.asarray(search.ranks), np.asarray(search.keys), search.view  # indexing a mapped array as such is slower
        self.careful = search.has_zero

    def _next(self, at: np.ndarray) -> np.ndarray:
        """Eight bytes of the dictionary at some places, zeros beyond its end."""
        return self.view[np.minimum(at, self.m)].astype(np.uint64)

    def _place(self, rank: np.ndarray) -> np.ndarray:
        return self.sa[np.minimum(rank, self.m - 1)].astype(np.int64)

    def _settle(self, r: np.ndarray, high, depth: int, want: np.ndarray, need: np.ndarray) -> np.ndarray:
        """Ranks moved over suffixes that look equal but end before ``need`` bytes; there are fewer than eight of them at a depth."""
        while self.careful:
            at = self._place(r) + depth
            early = (r < high) & (self.m - at < need) & (self._next(at) == want)
            if not early.any():
                break
            r = r + early
        return r

    def _bound(self, low: np.ndarray, high: np.ndarray, depth: int, want: np.ndarray, upper: bool) -> np.ndarray:
        """First rank in [low, high) whose eight bytes at ``depth`` are not below (or, ``upper``, are above) the wanted ones."""
        low, high = low.copy(), high.copy()
        open_ = np.flatnonzero(low < high)
        while len(open_):
            mid = (low[open_] + high[open_]) >> 1
            got = self._next(self._place(mid) + depth)
            right = got <= want[open_] if upper else got < want[open_]
            low[open_[right]] = mid[right] + 1
            high[open_[~right]] = mid[~right]
            open_ = open_[low[open_] < high[open_]]
        return low

    def _shared(self, rank: np.ndarray, ok: np.ndarray, depth: int, want: np.ndarray, room: np.ndarray) -> np.ndarray:
        """Bytes that the suffix of a rank shares with the wanted ones at ``depth``."""
        at = self._place(np.maximum(rank, 0))
        got = self.keys[np.clip(rank, 0, self.m - 1)] if depth == 0 else self._next(at + depth)
        n = np.minimum(_equal_bytes(got, want), np.minimum(np.maximum(self.m - at - depth, 0), room))
        return np.where(ok, n, 0)

    def lengths(self, ahead: Ahead, at: np.ndarray, end: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Length of the longest match at each place, at most ``most``; which ones have that, and the ranks [low, high) of the suffixes that share so much with them.

        Places are best sorted by what follows them.
        """
        room = np.minimum(end - at, 8)
        want = ahead[at] & _MASK[room]
        r = self._settle(np.searchsorted(self.keys, want), self.m, 0, want, room)
        total = np.maximum(self._shared(r, r < self.m, 0, want, room), self._shared(r - 1, r > 0, 0, want, room))
        go = np.flatnonzero(total == 8)
        low, high, depth = r[go], np.searchsorted(self.keys, want[go], side="right"), 8
        while len(go) and depth < most:
            room = np.minimum(end[go] - at[go] - depth, 8)
            want = ahead[at[go] + depth] & _MASK[room]
            r = self._settle(self._bound(low, high, depth, want, False), high, depth, want, room)
            n = np.maximum(self._shared(r, r < high, depth, want, room), self._shared(r - 1, r > low, depth, want, room))
            total[go] += n
            more = np.flatnonzero(n == 8)
            high = self._bound(r[more], high[more], depth, want[more], True)
            low, go, depth = r[more], go[more], depth + 8
        return total, go, low, high

    def first(self, ahead: Ahead, at: np.ndarray, length: np.ndarray) -> np.ndarray:
        """Rank of the least suffix that begins with the ``length`` bytes at each place; such a suffix exists."""
        need = np.minimum(length, 8)
        want = ahead[at] & _MASK[need]
        rank = self._settle(np.searchsorted(self.keys, want), self.m, 0, want, need)
        go, depth = np.flatnonzero(length > 8), 8
        low, high = rank[go], np.searchsorted(self.keys, want[go], side="right")
        while len(go):
            need = np.minimum(length[go] - depth, 8)
            want = ahead[at[go] + depth] & _MASK[need]
            r = self._settle(self._bound(low, high, depth, want, False), high, depth, want, need)
            rank[go] = r
            more = np.flatnonzero(length[go] > depth + 8)
            high = self._bound(r[more], high[more], depth, want[more], True)
            low, go, depth = r[more], go[more], depth + 8
        return rank

    def last(self, ahead: Ahead, at: np.ndarray, length: np.ndarray, rank: np.ndarray) -> np.ndarray:
        """The rank after that of the last suffix that begins with the ``length`` bytes at each place; the first one's rank is given."""
        need = np.minimum(length, 8)
        # the greatest eight bytes that begin so
        most = (ahead[at] & _MASK[need]) | ~_MASK[need]
        high = np.searchsorted(self.keys, most, side="right")
        go, depth = np.flatnonzero(length > 8), 8
        low = rank[go]
        while len(go):
            need = np.minimum(length[go] - depth, 8)
            most = (ahead[at[go] + depth] & _MASK[need]) | ~_MASK[need]
            high[go] = self._bound(low, high[go], depth, most, True)
            more = np.flatnonzero(length[go] > depth + 8)
            low, go, depth = low[more], go[more], depth + 8
        return high

    def leftmost(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """The least place of the ranks [low, high)."""
        levels, out = self.search.least_places, np.empty(len(low), np.int64)
        first, stop = -(-low // LEAST), high // LEAST
        inside = first < stop
        ends = np.arange(LEAST)
        for i in range(0, len(low), 1 << 14):
            s = slice(i, i + (1 << 14))
            # what lies before the first and after the last whole block; a short run has both in one
            a = np.minimum(low[s, None] + ends, np.where(inside[s], first[s] * LEAST, high[s])[:, None] - 1)
            b = np.minimum(np.where(inside[s], stop[s] * LEAST, first[s] * LEAST)[:, None] + ends, high[s, None] - 1)
            a, b = np.maximum(a, low[s, None]), np.maximum(b, low[s, None])
            out[s] = np.minimum(self.sa[a].min(1), self.sa[b].min(1))
        go = np.flatnonzero(inside)
        k = np.frexp((stop[go] - first[go]).astype(float))[1] - 1
        for n in np.unique(k).tolist():
            w = go[k == n]
            out[w] = np.minimum(out[w], np.minimum(levels[n][first[w]], levels[n][stop[w] - (1 << n)]))
        return out

    def _walks(self, text: bytes, ahead: Ahead, at: np.ndarray, end: np.ndarray, a: int, b: int) -> tuple[np.ndarray, np.ndarray, dict[int, tuple[int, int]]]:
        """(lengths of the longest matches, ``DEEP`` at most; steps; the longer matches alone) at the places ``at`` of the window [a, b) and at all that greedy
        walks from there come to. Steps are 0 elsewhere.

        All walks take a step together, and one ends where another has been. Walks that begin apart soon meet.
        """
        k, steps, alone = np.zeros(b - a, np.int32), np.zeros(b - a, np.int32), {}
        while len(at):
            at = at[np.argsort(ahead[at])]
            stop = end[np.searchsorted(end, at + a, side="right")] - a
            got, *deep = self.lengths(ahead, at, stop, DEEP)
            step = np.maximum(got, 1)
            for j, *within in zip(*(x.tolist() for x in deep), strict=True):
                p = int(at[j]) + a
                alone[p] = self.search.longest_match(text, p, int(stop[j]) + a, within)
                step[j] = alone[p][1]
            k[at], steps[at] = got, step
            at = at + step
            at = at[at < b - a]
            at = np.sort(at[steps[at] == 0])
            at = at[np.diff(at, prepend=-1) > 0]
        return k, steps, alone

    def factors(self, bodies: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(pos, len, cuts): the factors of document i are those from cuts[i] to cuts[i + 1]."""
        text = b"".join(bodies)
        whole = np.frombuffer(text, np.uint8)
        off = np.concatenate([[0], np.cumsum([len(x) for x in bodies])]).astype(np.int64)
        if not self.m:
            return whole.astype(np.int64), np.zeros(len(whole), np.int64), off
        self.careful = self.search.has_zero or b"\0" in text
        end = off[1:]
        starts, pos, length, i = [], [], [], 0
        for a in range(0, len(whole), WINDOW):
            b = min(a + WINDOW, len(whole))
            if i >= b:
                continue
            ahead = Ahead(whole[a : b + DEEP + 8])
            at = np.concatenate([off[np.searchsorted(off, i) : np.searchsorted(off, b)], np.arange(i, b, STRIDE)])
            k, steps, alone = self._walks(text, ahead, np.unique(at) - a, end, a, b)
            steps, walked = memoryview(steps), []
            while i < b:
                walked.append(i)
                i += steps[i - a]
            walk = np.array(walked, np.int64)
            size = k[walk - a].astype(np.int64)
            known = np.flatnonzero((size > 0) & (size < DEEP))
            place = whole[walk].astype(np.int64)
            if len(known):
                known = known[np.argsort(ahead[walk[known] - a])]
                rank = self.first(ahead, walk[known] - a, size[known])
                place[known] = self._place(rank) if self.tie == "first_rank" else self.leftmost(rank, self.last(ahead, walk[known] - a, size[known], rank))
            for j in np.flatnonzero(size == DEEP).tolist():
                p, n = alone[walked[j]]
                place[j], size[j] = p if self.tie == "first_rank" else self.search.leftmost(text[walked[j] : walked[j] + n]), n
            starts.append(walk)
            pos.append(place)
            length.append(size)
        if not starts:
            return np.empty(0, np.int64), np.empty(0, np.int64), np.zeros(len(bodies) + 1, np.int64)
        return np.concatenate(pos), np.concatenate(length), np.searchsorted(np.concatenate(starts), off)
