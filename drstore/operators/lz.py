"""Self-referring methods: a sliding window, phrases that end where phrases end, and a grammar of pairs."""

from __future__ import annotations

from bisect import bisect_right
from collections import Counter


def window_lz(x: bytes, window: int = 1 << 15, longest: int = 258) -> list[tuple[int, int, int]]:
    """(distance, length, next byte or -1): longest earlier copy that begins inside the window; chains of equal 3-byte strings."""
    chains: dict[bytes, list[int]] = {}
    out, i, n = [], 0, len(x)
    while i < n:
        best, where = 0, 0
        for p in reversed(chains.get(x[i : i + 3], [])):
            if i - p > window:
                break
            k = 3
            while k < longest and i + k < n and x[p + k] == x[i + k]:
                k += 1
            if k > best:
                best, where = k, i - p
                if best == longest:
                    break
        after = i + best
        out.append((where, best, x[after] if after < n else -1))
        for j in range(i, min(after + 1, n)):
            chains.setdefault(x[j : j + 3], []).append(j)
        i = after + 1
    return out


def undo_window_lz(parts: list[tuple[int, int, int]]) -> bytes:
    out = bytearray()
    for d, k, c in parts:
        for _ in range(k):
            out.append(out[-d])
        if c >= 0:
            out.append(c)
    return bytes(out)


def end_aligned(x: bytes) -> list[tuple[int, int, int]]:
    """(phrase, length, next byte): a phrase copies a string that ends where an earlier phrase ends, so any part can be opened backwards.

    Needs all of the text at once; for small texts.
    """
    out: list[tuple[int, int, int]] = []
    # the first phrase that ends with a string of up to eight bytes; (phrase, where it ends) by its last 8, 16, 32, ... bytes
    first: list[dict[bytes, int]] = [{} for _ in range(9)]
    by_last: list[dict[bytes, list[tuple[int, int]]]] = [{}]
    i, n = 0, len(x)
    while i < n:
        best, phrase, most, p = 0, 0, 0, 0
        while i + most < n - 1 and (p := x.find(x[i : i + most + 1], p, i)) >= 0:  # no copy is longer than one that ends anywhere
            most += 1
            while i + most < n - 1 and p + most < i and x[p + most] == x[i + most]:
                most += 1
        while 8 << len(by_last) <= most:
            q = 8 << len(by_last)
            grams: dict[bytes, list[tuple[int, int]]] = {}
            at = 0
            for j, (_, k, c) in enumerate(out):
                at += k + (c >= 0)
                if at >= q:
                    grams.setdefault(x[at - q : at], []).append((j, at))
            by_last.append(grams)
        for k in range(most, 8, -1):
            level = min((k >> 3).bit_length(), len(by_last)) - 1
            near = by_last[level].get(x[i + k - (8 << level) : i + k])
            if near:
                s = x[i : i + k]
                number = next((j for j, e in near if e >= k and x[e - k : e] == s), None)
                if number is not None:
                    best, phrase = k, number
                    break
        else:
            for k in range(min(most, 8), 0, -1):
                number = first[k].get(x[i : i + k])
                if number is not None:
                    best, phrase = k, number
                    break
        c = x[i + best] if i + best < n else -1
        out.append((phrase, best, c))
        i += best + 1
        e = min(i, n)
        number = len(out) - 1
        for k in range(1, min(e, 8) + 1):
            first[k].setdefault(x[e - k : e], number)
        for level, grams in enumerate(by_last):
            if e >= 8 << level:
                grams.setdefault(x[e - (8 << level) : e], []).append((number, e))
    return out


def open_end_aligned(parts: list[tuple[int, int, int]], start: int, size: int) -> bytes:
    """Bytes start..start+size without opening what comes before."""
    ends, at = [], 0
    for _, k, c in parts:
        at += k + (c >= 0)
        ends.append(at)
    out = bytearray(size)
    # (where it goes, where it is, bytes); what is opened already is copied
    todo = [(0, start, size)]
    done = 0
    while todo:
        to, i, n = todo.pop()
        while n:
            if start <= i and i + n <= start + done:
                out[to : to + n] = out[i - start : i - start + n]
                n = 0
                continue
            number = bisect_right(ends, i)
            phrase, k, c = parts[number]
            if c >= 0 and i == ends[number] - 1:
                out[to] = c
                got = 1
            else:
                begin = ends[number] - k - (c >= 0)
                got = min(n, begin + k - i)
                if got < n:
                    todo.append((to + got, i + got, n - got))
                i, n = ends[phrase] - k + (i - begin), got
                continue
            to, i, n = to + got, i + got, n - got
        done = todo[-1][0] if todo else size
    return bytes(out)


def pair_grammar(x: bytes, rounds: int) -> tuple[list[int], list[tuple[int, int]]]:
    """(sequence, rules): the most frequent pair of neighbours becomes a symbol (256 and up), again and again."""
    seq, rules = list(x), []
    for _ in range(rounds):
        pairs = Counter(zip(seq, seq[1:], strict=False))
        if not pairs:
            break
        pair, c = max(pairs.items(), key=lambda p: (p[1], p[0]))
        if c < 2:
            break
        new, out, i = 256 + len(rules), [], 0
        rules.append(pair)
        while i < len(seq):
            if i + 1 < len(seq) and (seq[i], seq[i + 1]) == pair:
                out.append(new)
                i += 2
            else:
                out.append(seq[i])
                i += 1
        seq = out
    return seq, rules


def undo_pair_grammar(seq: list[int], rules: list[tuple[int, int]]) -> bytes:
    out, stack = bytearray(), list(reversed(seq))
    while stack:
        s = stack.pop()
        if s < 256:
            out.append(s)
        else:
            a, b = rules[s - 256]
            stack += [b, a]
    return bytes(out)
