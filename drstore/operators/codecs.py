"""Integer codes and pair codecs.

U: unsigned 32-bit little-endian. V: seven bits a byte from the lowest, high bit set when more follow. Z: zlib level 9 over the U form (or the V form) of a
stream. S: words of 32 bits whose upper 4 select one of nine splits of the 28 others. P: blocks of 128, each with a width that
holds nine tenths of its values, the others patched from a list. F: as many bits a value as the largest position needs.

A pair codec is two letters, for positions and lengths; ``Zi`` is one zlib stream over interleaved pairs.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Callable

import numpy as np

#: fixed values of the selector code: (values in a word, bits of each)
SPLITS = ((28, 1), (14, 2), (9, 3), (7, 4), (5, 5), (4, 7), (3, 9), (2, 14), (1, 28))
PATCH_BLOCK = 128


def enc_u(v: np.ndarray) -> bytes:
    return np.asarray(v, "<u4").tobytes()


def dec_u(b: bytes) -> np.ndarray:
    return np.frombuffer(b, "<u4").astype(np.int64)


def enc_v(v: np.ndarray) -> bytes:
    v = np.asarray(v, np.uint64)
    if not len(v):
        return b""
    size = 1 + sum((v >= np.uint64(1 << (7 * k))).astype(np.int64) for k in range(1, 5))
    end = np.cumsum(size)
    out = np.zeros(int(end[-1]), np.uint8)
    for k in range(5):
        has = size > k
        byte = (v[has] >> np.uint64(7 * k)) & np.uint64(127)
        out[(end - size)[has] + k] = byte.astype(np.uint8) | np.where(size[has] > k + 1, 128, 0).astype(np.uint8)
    return out.tobytes()


def dec_v(b: bytes) -> np.ndarray:
    a = np.frombuffer(b, np.uint8)
    if not len(a):
        return np.empty(0, np.int64)
    last = a < 128
    number = np.concatenate([[0], np.cumsum(last)[:-1]])
    start = np.concatenate([[0], np.flatnonzero(last)[:-1] + 1])
    shift = 7 * (np.arange(len(a)) - start[number])
    out = np.zeros(int(last.sum()), np.int64)
    np.add.at(out, number, (a & 127).astype(np.int64) << shift)
    return out


def enc_z(v: np.ndarray, form: str = "u32") -> bytes:
    return zlib.compress(enc_u(v) if form == "u32" else enc_v(v), 9)


def dec_z(b: bytes, form: str = "u32") -> np.ndarray:
    raw = zlib.decompress(b)
    return dec_u(raw) if form == "u32" else dec_v(raw)


def enc_s(v: np.ndarray) -> bytes:
    """Selector words; values of 28 bits or more follow a word of selector 9 as 32 bits."""
    v = [int(x) for x in v]
    out, i = [], 0
    while i < len(v):
        if v[i] >= 1 << 28:
            out += [9 << 28, v[i]]
            i += 1
            continue
        for k, (n, bits) in enumerate(SPLITS):
            part = v[i : i + n]
            if all(x < 1 << bits for x in part):
                word = k << 28
                for j, x in enumerate(part):
                    word |= x << (j * bits)
                out.append(word)
                i += len(part)
                break
    return struct.pack("<I", len(v)) + np.array(out, "<u4").tobytes()


def dec_s(b: bytes) -> np.ndarray:
    total, words = struct.unpack_from("<I", b)[0], np.frombuffer(b, "<u4", offset=4).tolist()
    out: list[int] = []
    i = 0
    while len(out) < total:
        k = words[i] >> 28
        if k == 9:
            out.append(words[i + 1])
            i += 2
            continue
        n, bits = SPLITS[k]
        out += [(words[i] >> (j * bits)) & ((1 << bits) - 1) for j in range(min(n, total - len(out)))]
        i += 1
    return np.array(out, np.int64)


def _bits(v: np.ndarray, width: int) -> bytes:
    if not width:
        return b""
    shifts = np.arange(width, dtype=np.uint64)
    return np.packbits(((v.astype(np.uint64)[:, None] >> shifts) & np.uint64(1)).astype(np.uint8)).tobytes()


def _unbits(b: bytes, n: int, width: int) -> np.ndarray:
    if not width:
        return np.zeros(n, np.int64)
    bits = np.unpackbits(np.frombuffer(b, np.uint8), count=n * width).reshape(n, width).astype(np.int64)
    return (bits << np.arange(width)).sum(1)


def enc_p(v: np.ndarray) -> bytes:
    v = np.asarray(v, np.int64)
    out = [struct.pack("<I", len(v))]
    for i in range(0, len(v), PATCH_BLOCK):
        part = v[i : i + PATCH_BLOCK]
        low = int(part.min())
        rest = part - low
        width = int(np.sort(rest)[(len(rest) * 9 - 1) // 10]).bit_length()
        odd = np.flatnonzero(rest >= 1 << width)
        body = _bits(np.where(rest >= 1 << width, 0, rest), width)
        out += [struct.pack("<IBB", low, width, len(odd)), body, odd.astype(np.uint8).tobytes(), enc_v(rest[odd])]
    return b"".join(out)


def dec_p(b: bytes) -> np.ndarray:
    n, at = struct.unpack_from("<I", b)[0], 4
    out = []
    for i in range(0, n, PATCH_BLOCK):
        k = min(PATCH_BLOCK, n - i)
        low, width, odd = struct.unpack_from("<IBB", b, at)
        at += 6
        size = (k * width + 7) // 8
        part = _unbits(b[at : at + size], k, width)
        at += size
        where = np.frombuffer(b, np.uint8, odd, at)
        at += odd
        end, left = at, odd
        while left:
            left -= b[end] < 128
            end += 1
        part[where] = dec_v(b[at:end])
        at = end
        out.append(part + low)
    return np.concatenate(out) if out else np.empty(0, np.int64)


def enc_f(v: np.ndarray) -> bytes:
    v = np.asarray(v, np.int64)
    width = int(v.max()).bit_length() if len(v) else 0
    return struct.pack("<IB", len(v), width) + _bits(v, width)


def dec_f(b: bytes) -> np.ndarray:
    n, width = struct.unpack_from("<IB", b)
    return _unbits(b[5:], n, width)


CODES: dict[str, tuple[Callable, Callable]] = {"U": (enc_u, dec_u), "V": (enc_v, dec_v), "Z": (enc_z, dec_z), "S": (enc_s, dec_s), "P": (enc_p, dec_p), "F": (enc_f, dec_f)}

#: the pair codecs of the experiments, and the rest of their grid
PAIR_CODECS = ("ZZ", "ZV", "UZ", "UV")
GRID = tuple(a + b for a in "UVZ" for b in "UVZ")


def encode_stream(v: np.ndarray, letter: str, z_form: str = "u32") -> bytes:
    return enc_z(v, z_form) if letter == "Z" else CODES[letter][0](v)


def encode_pairs(pos: np.ndarray, length: np.ndarray, codec: str, z_form: str = "u32") -> tuple[bytes, bytes]:
    if codec == "Zi":
        both = np.empty(2 * len(pos), np.int64)
        both[::2], both[1::2] = pos, length
        return enc_z(both), b""
    first, second = (encode_stream(v, letter, z_form) for letter, v in zip(codec, (pos, length), strict=True))
    return first, second


def decode_pairs(pos: bytes, length: bytes, codec: str, z_form: str = "u32") -> tuple[np.ndarray, np.ndarray]:
    if codec == "Zi":
        both = dec_z(pos)
        return both[::2], both[1::2]
    out = []
    for letter, b in zip(codec, (pos, length), strict=True):
        out.append(dec_z(b, z_form) if letter == "Z" else CODES[letter][1](b))
    return out[0], out[1]
