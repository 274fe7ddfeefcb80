"""Language identification by interpolated Kneser-Ney character models.

Characters are folded to 12-bit codes; words are runs of letters with a boundary on both sides, and the model of a language
gives each character (and the closing boundary) a probability given up to ``ORDER - 1`` characters of the same word before it.
Raw counts are kept at the highest order, counts of distinct left neighbours below it, with one absolute discount
for each order and language. The n-grams of all languages share one sorted hash array for each order, with a column of log-probabilities
for each language; contexts have arrays of back-off weights. The language with the least cross-entropy per character wins.

``score`` is the calibrated probability that this is right: a logistic curve over the margin to the second
language and the length, fitted on labelled documents that the counts did not use; below ``reject_below`` the prediction is marked ``rejected``.

Training takes about ``max_rows`` labelled documents of a language (the ones whose hash falls under a rate), so the model's size has a bound.
Prediction reads whole texts and uses nothing but the text. Null text or text without a letter: ``und``, score 0. Null doc_id: predicted, never
learned from. Without labelled rows all is ``und``. Repeated rows give repeated results.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textkit as tk

ORDER, BITS, EDGE = 4, 12, 1
_MASK = (1 << BITS) - 1
CACHE_SLOTS = 1 << 19

_folded: np.ndarray | None = None


def fold_table() -> np.ndarray:
    """Code of each code point: 0 for what is no letter, lower case for Latin capitals, hashed above 0xF00."""
    global _folded
    if _folded is None:
        cp = np.arange(0x110000, dtype=np.int64)
        code = np.where(cp < 0xF00, cp, 0xF00 + (cp * 2654435761 >> 7) % 256)
        code[65:91] += 32
        code[0xC0:0xDF] += 32
        alpha = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)
        code[~alpha] = 0
        _folded = code.astype(np.uint64)
    return _folded


def letter_grams(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ORDER-gram key of each character and closing edge, index of its word, letters of each word)."""
    points = np.frombuffer(b" ".join(words).decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    code = fold_table()[points]
    word = np.cumsum(points == 0x20) if len(points) else np.empty(0, np.int64)
    letter = code > 0
    letters = np.bincount(word[letter], minlength=len(words)) if len(words) else np.empty(0, np.int64)
    # one closing edge after each run of letters, ORDER - 1 opening edges taken as padding
    begin = letter.copy()
    begin[1:] &= ~letter[:-1]
    run = np.cumsum(begin) - 1
    seq, owner, run = code[letter], word[letter], run[letter]
    if not len(seq):
        return np.empty(0, np.uint64), np.empty(0, np.int64), letters
    last = np.append(run[1:] != run[:-1], True)
    at = np.arange(len(seq)) + np.concatenate([[0], np.cumsum(last)[:-1]])
    n = len(seq) + int(last.sum())
    flat, who, rid = np.full(n, EDGE, np.uint64), np.zeros(n, np.int64), np.zeros(n, np.int64)
    flat[at], who[at], rid[at] = seq, owner, run
    ends = at[last] + 1
    who[ends], rid[ends] = owner[last], run[last]
    key = flat.copy()
    for k in range(1, ORDER):
        back = np.full(n, EDGE, np.uint64)
        back[k:] = np.where(rid[k:] == rid[:-k], flat[:-k], EDGE)
        key |= back << np.uint64(BITS * k)
    return key, who, letters


@dataclass
class Model:
    langs: list[str]
    keys: list[np.ndarray]  # by order 1..ORDER, sorted
    logp: list[np.ndarray]  # (keys, langs)
    contexts: list[np.ndarray]  # by order, sorted
    backoff: list[np.ndarray]
    curve: tuple[float, float, float] = (0.0, 8.0, 0.3)

    def grams(self, key: np.ndarray) -> np.ndarray:
        """Natural-log probability of each ORDER-gram's last character, for each language."""
        out = np.zeros((len(key), len(self.langs)), np.float32)
        open_ = np.arange(len(key))
        for n in range(ORDER, 0, -1):
            if not len(open_):
                break
            k = key[open_] & np.uint64((1 << (BITS * n)) - 1)
            i = np.minimum(np.searchsorted(self.keys[n - 1], k), len(self.keys[n - 1]) - 1)
            hit = self.keys[n - 1][i] == k
            out[open_[hit]] += self.logp[n - 1][i[hit]]
            open_, k = open_[~hit], k[~hit]
            c = k >> np.uint64(BITS)
            i = np.minimum(np.searchsorted(self.contexts[n - 1], c), len(self.contexts[n - 1]) - 1)
            hit = self.contexts[n - 1][i] == c
            out[open_[hit]] += self.backoff[n - 1][i[hit]]
        out[open_] += np.float32(-np.log(1 << BITS))
        return out

    def words(self, words: list[bytes]) -> np.ndarray:
        """(words, langs + 2): log-probabilities, characters scored, letters."""
        out = np.zeros((len(words), len(self.langs) + 2), np.float32)
        if not words:
            return out
        key, who, letters = letter_grams(words)
        if len(key):
            uniq, inverse = np.unique(key, return_inverse=True)
            lp = self.grams(uniq)[inverse]
            for n in range(len(self.langs)):
                out[:, n] = np.bincount(who, lp[:, n], minlength=len(words))
            out[:, -2] = np.bincount(who, minlength=len(words))
        out[:, -1] = letters
        return out

    def confidence(self, margin: np.ndarray, n: np.ndarray) -> np.ndarray:
        a, b, c = self.curve
        return 1 / (1 + np.exp(-np.clip(a + b * margin + c * np.log1p(n), -30, 30)))


def fit(counts: pd.DataFrame, langs: list[str]) -> Model:
    """counts: lang (index into langs), key (ORDER-gram as signed 64-bit), n."""
    L = len(langs)
    keys_at, logp_at, ctx_at, back_at = [], [], [], []
    key = counts["key"].to_numpy().astype(np.int64).view(np.uint64)
    uniq, inverse = np.unique(key, return_inverse=True)
    table = np.zeros((len(uniq), L))
    np.add.at(table, (inverse, counts["lang"].to_numpy()), counts["n"].to_numpy())
    levels = [(uniq, table)]
    for n in range(ORDER - 1, 0, -1):
        below = levels[0][0] & np.uint64((1 << (BITS * n)) - 1)
        u, inv = np.unique(below, return_inverse=True)
        t = np.zeros((len(u), L))
        np.add.at(t, inv, (levels[0][1] > 0).astype(float))
        levels.insert(0, (u, t))
    lower = None
    for n, (u, t) in enumerate(levels, 1):
        c, inv = np.unique(u >> np.uint64(BITS), return_inverse=True)
        total, kinds = np.zeros((len(c), L)), np.zeros((len(c), L))
        np.add.at(total, inv, t)
        np.add.at(kinds, inv, (t > 0).astype(float))
        n1, n2 = (t == 1).sum(0), (t == 2).sum(0)
        d = np.where(n1 + 2 * n2 > 0, n1 / np.maximum(n1 + 2 * n2, 1), 0.5)
        d = np.clip(d, 0.1, 0.95)
        gamma = np.where(total > 0, d * kinds / np.maximum(total, 1), 1.0)
        if lower is None:
            base = np.full((len(u), L), 1.0 / (1 << BITS))
        else:
            base = lower[np.searchsorted(levels[n - 2][0], u & np.uint64((1 << (BITS * (n - 1))) - 1))]
        p = np.where(total[inv] > 0, np.maximum(t - d, 0) / np.maximum(total[inv], 1), 0) + gamma[inv] * base
        keys_at.append(u)
        logp_at.append(np.log(p).astype(np.float32))
        ctx_at.append(c)
        back_at.append(np.log(gamma).astype(np.float32))
        lower = p
    return Model(langs, keys_at, logp_at, ctx_at, back_at)


class _Cache:
    """Direct-mapped table of word scores: fixed size, a new word takes the slot of an old one."""

    def __init__(self, model: Model):
        self.model = model
        self.tag = np.zeros(CACHE_SLOTS, np.uint64)
        self.value = np.zeros((CACHE_SLOTS, len(model.langs) + 2), np.float32)

    def scores(self, s: tk.Slab) -> np.ndarray:
        start, end = s.words()
        h = s.hash(start, end) | np.uint64(1)
        slot = (h >> np.uint64(40)).astype(np.int64) & (CACHE_SLOTS - 1)
        out = self.value[slot]
        miss = np.flatnonzero(self.tag[slot] != h)
        if len(miss):
            u, at, inverse = np.unique(h[miss], return_index=True, return_inverse=True)
            at = miss[at]
            flat = s.data.tobytes()
            v = self.model.words([flat[a:b] for a, b in zip(start[at].tolist(), end[at].tolist(), strict=True)])
            out[miss] = v[inverse]
            slot = (u >> np.uint64(40)).astype(np.int64) & (CACHE_SLOTS - 1)
            self.tag[slot] = 0
            self.value[slot] = v
            self.tag[slot] = u
            self.value[slot] = v
        return out


def slab_scores(cache: _Cache, s: tk.Slab) -> np.ndarray:
    """(documents, langs + 2) sums of word scores."""
    v = cache.scores(s)
    cuts = s.per_doc(s.words()[0])
    run = np.zeros((len(v) + 1, v.shape[1]))
    np.cumsum(v, axis=0, dtype=float, out=run[1:])
    return run[cuts[1:]] - run[cuts[:-1]]


def decide(model: Model, sums: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(language index or -1, confidence, cross-entropy in nats a character)."""
    n = np.maximum(sums[:, -2], 1)
    entropy = -sums[:, :-2] / n[:, None]
    best = entropy.argmin(1)
    part = np.sort(entropy, axis=1)
    margin = part[:, 1] - part[:, 0] if entropy.shape[1] > 1 else np.ones(len(best))
    conf = model.confidence(margin, sums[:, -2])
    none = sums[:, -1] == 0
    best[none] = -1
    return best, np.where(none, 0.0, conf), np.where(none, 0.0, part[:, 0])


def _count(langs: list[str]):
    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lang = np.array([langs.index(x) for x in b.column(0).to_pylist()], np.int64)
            for i, j, s in tk.slabs(b.column(1)):
                start, end = s.words()
                doc = np.repeat(np.arange(i, j), np.diff(s.per_doc(start)))
                flat = s.data.tobytes()
                key, who, _ = letter_grams([flat[a:e] for a, e in zip(start.tolist(), end.tolist(), strict=True)])
                of = lang[doc][who] if len(key) else np.empty(0, np.int64)
                for n in np.unique(of).tolist():
                    u, c = np.unique(key[of == n], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(u), n, np.int32)), pa.array(u.view(np.int64)), pa.array(c.astype(np.int64))], names=["lang", "key", "n"])

    return run


def _bucket(mod: int) -> Column:
    return F.crc32(F.col("doc_id").cast("string")) % mod


def train(docs: DataFrame, fold: int = 5, max_rows: int = 1500) -> Model | None:
    """Learn from rows with non-null lang whose crc32(doc_id as text) mod ``fold`` is not 0; a sixth of the sample is for calibration."""
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"), docs["lang"].cast("string").alias("lang")).where((_bucket(fold) != 0) & F.col("lang").isNotNull())
    sizes = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}
    if not sizes:
        return None
    langs = sorted(sizes)
    u = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) / float(1 << 30)
    rate = F.element_at(F.create_map(*(F.lit(x) for k, v in sizes.items() for x in (k, float(max_rows) / v))), F.col("lang"))
    sample = rows.where(u < rate)
    calibrate = F.pmod(F.xxhash64(F.col("doc_id"), F.col("text"), F.lit(1)), F.lit(6)) == 0
    counted = sample.where(~calibrate).select("lang", "text").mapInArrow(_count(langs), "lang int, key long, n long").groupBy("lang", "key").agg(F.sum("n").alias("n")).toPandas()
    if counted.empty:
        return None
    m = fit(counted, langs)

    @tk.tidy
    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _Cache(m)
        for b in batches:
            for i, j, s in tk.slabs(b.column(1)):
                sums = slab_scores(cache, s)
                best, _, _ = decide(m, sums)
                part = np.sort(-sums[:, :-2] / np.maximum(sums[:, -2:-1], 1), axis=1)
                margin = part[:, 1] - part[:, 0] if part.shape[1] > 1 else np.ones(len(best))
                right = [best[k] >= 0 and m.langs[best[k]] == x for k, x in enumerate(b.column(0).slice(i, j - i).to_pylist())]
                yield pa.RecordBatch.from_arrays([pa.array(margin), pa.array(sums[:, -2]), pa.array(np.array(right, float))], names=["margin", "n", "right"])

    got = sample.where(calibrate).select("lang", "text").mapInArrow(held, "margin double, n double, right double").toPandas()
    if len(got):
        m.curve = _logistic(got["margin"].to_numpy(), np.log1p(got["n"].to_numpy()), got["right"].to_numpy())
    return m


def _logistic(margin: np.ndarray, length: np.ndarray, right: np.ndarray) -> tuple[float, float, float]:
    """Ridge-held Newton steps; slopes are kept from falling below 0."""
    x = np.column_stack([np.ones(len(margin)), margin, length])
    w, ridge = np.zeros(3), np.diag([0.01, 0.01, 0.1])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w = w + np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge, x.T @ (right - p) - ridge @ w)
    return float(w[0]), float(max(w[1], 0)), float(max(w[2], 0))


_caches: dict[str, _Cache] = {}


def predict(docs: DataFrame, model: Model | None, reject_below: float = 0.5, text: str = "text") -> DataFrame:
    """doc_id, lang_pred, score, cross_entropy (nats a character), rejected."""
    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs[text].cast("string").alias("text"))
    if model is None:
        return src.select("doc_id", F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"), F.lit(0.0).alias("cross_entropy"), F.lit(True).alias("rejected"))
    import uuid

    shipped, ident = src.sparkSession.sparkContext.broadcast(model), uuid.uuid4().hex

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if ident not in _caches:
            _caches.clear()
            _caches[ident] = _Cache(shipped.value)
        cache = _caches[ident]
        names = [*cache.model.langs, "und"]
        for b in batches:
            for i, j, s in tk.slabs(b.column(1)):
                best, conf, entropy = decide(cache.model, slab_scores(cache, s))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array([names[k] for k in best.tolist()], pa.string()), pa.array(conf), pa.array(entropy), pa.array(conf < reject_below)], names=["doc_id", "lang_pred", "score", "cross_entropy", "rejected"])

    return src.mapInArrow(run, "doc_id long, lang_pred string, score double, cross_entropy double, rejected boolean")
