"""Secret scans: fixed patterns, and a battery of randomness tests under false-discovery control.

Fixed patterns give the base spans. The method then looks at every maximal run of ``[A-Za-z0-9+/_=-]`` of ``MIN_RUN`` or
more characters, or what base spans leave of it: the part outside, or the whole run where a hex span alone leaves a part shorter
than that (only the part outside becomes a span). Its encoding is inferred (hex, base32, base64 or decimal), and three tests ask
whether it looks like uniform draws from that alphabet: chi-squared over the symbols, the number of runs above and
below the middle of the alphabet, and the lag-one serial correlation. For chi-squared the symbols stand in the order of how common letters are in
ordinary text, so that classes of neighbours tell text from chance also in short runs. The tail probabilities are joined into one score; a
high score means that uniform randomness is not refuted.

What score is rare for ordinary text depends on length, so the control is by bands of length. Every run has up to ``DECOYS`` decoys of its own make: of the same
length, with a digit, a capital, a small letter or a sign in the same places, but letters taken in turn from the neighbouring words (those
that the run's encoding has) and digits from neighbouring or ordinary numbers. So a decoy differs from a run in nothing but where its symbols come from.
``REFERENCE`` runs of ordinary words and names a band join them, so that a
small table has a tail to compare with. The empirical p-value of a score is the decoys' share at or above it, with one added, in its band and the
two beside it; the Benjamini-Hochberg rule over all runs, at ``fdr``, says which p-values pass. So one clear secret passes by
itself; short ones need company or luck. The histograms (bands x score bins) come from all documents and have a fixed size.

Null text is empty text and has no spans. Rows are independent of each other but for the thresholds; repeated rows give
repeated results; an empty table gives an empty one; null doc_id is carried. Spans are in code points, end exclusive. A run meets the spans beside it
alone, so a very long text costs no more a character than a short one.
"""

from __future__ import annotations

import functools
import hashlib
import itertools
import math
import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared
from . import textkit as tk

KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
MIN_ASSIGN, MIN_ACCESS, MIN_HEX, MIN_RUN = 12, 18, 16, 20
_WORDS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
BINS = 40
BANDS = 8
DECOYS, REFERENCE = 32, 1000

_HEX = np.zeros(256, bool)
_HEX[list(b"0123456789abcdef")] = True
_RUN = np.zeros(256, bool)
_RUN[[*range(48, 58), *range(65, 91), *range(97, 123), *b"+/_=-"]] = True

#: alphabets from the narrowest
_ALPHABETS = (("decimal", b"0123456789"), ("hex", b"0123456789abcdef"), ("hex", b"0123456789ABCDEF"), ("base32", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"), ("base64", b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"), ("base64url", b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-_"))


def _upper_normal(z: float) -> float:
    return 0.5 * math.erfc(z / math.sqrt(2))


def _chi2_tail(x: float, k: int) -> float:
    """Upper tail of chi-squared by the cube-root normal approximation."""
    if x <= 0:
        return 1.0
    return _upper_normal(((x / k) ** (1 / 3) - (1 - 2 / (9 * k))) / math.sqrt(2 / (9 * k)))


def infer_encoding(token: bytes) -> tuple[str, bytes]:
    body = set(token.rstrip(b"="))
    for name, letters in _ALPHABETS:
        if body <= set(letters):
            return name, letters
    return "base64url", _ALPHABETS[-1][1] + b"+/="


#: letters from the most to the least common, over several languages
_COMMON = "eaitnorsldcumphgbfvwkyzjxq"


@functools.cache
def common_first(letters: bytes) -> np.ndarray:
    """The place of each symbol of an alphabet when the most common letters come first, both cases together, and digits and signs last."""
    order = sorted(range(len(letters)), key=lambda i: (_COMMON.find(chr(letters[i]).lower()) % 99, letters[i]))
    return np.argsort(order)


def randomness(token: bytes) -> tuple[str, float, float, float]:
    """(encoding, p of chi-squared uniformity, p of the runs test, p of serial correlation)."""
    name, letters = infer_encoding(token)
    index = {c: i for i, c in enumerate(letters)}
    v = np.array([index[c] for c in token.rstrip(b"=") if c in index], float)
    n, a = len(v), len(letters)
    if n < 2:
        return name, 1.0, 1.0, 1.0
    # symbols are pooled into at most n / 4 classes so that each has some expected count
    classes = max(2, min(a, n // 4))
    of = common_first(letters) * classes // a
    got, share = np.bincount(of[v.astype(int)], minlength=classes), np.bincount(of, minlength=classes) / a
    p_chi = _chi2_tail(float(((got - n * share) ** 2 / (n * share)).sum()), classes - 1)
    up = v >= a / 2
    n1, n2 = int(up.sum()), int(n - up.sum())
    if n1 and n2:
        runs = 1 + int((up[1:] != up[:-1]).sum())
        mean = 1 + 2 * n1 * n2 / n
        var = (mean - 1) * (mean - 2) / (n - 1)
        p_runs = math.erfc(abs(runs - mean) / math.sqrt(2 * var)) if var > 0 else 1.0
    else:
        p_runs = 2.0 ** (1 - n)
    spread = v - (a - 1) / 2
    corr = float((spread[1:] * spread[:-1]).sum()) / (n - 1) / ((a * a - 1) / 12)
    p_corr = math.erfc(abs(corr) * math.sqrt(n - 1) / math.sqrt(2))
    return name, p_chi, p_runs, p_corr


def score(token: bytes) -> float:
    """0 (plainly not random) to 1: Fisher's joint tail probability of the three tests, times the share of character classes seen.

    A uniform string of some length in a mixed alphabet shows digits and both cases; text seldom does.
    """
    name, *ps = randomness(token)
    x = -2 * sum(math.log(max(p, 1e-300)) for p in ps)
    h = x / 2
    joint = math.exp(-h) * (1 + h + h * h / 2) if h < 700 else 0.0
    classes = [any(48 <= c < 58 for c in token), any(65 <= c < 91 for c in token), any(97 <= c < 123 for c in token)]
    want = {"decimal": 1, "hex": 2, "base32": 2}.get(name, 3)
    return joint * min(1.0, sum(classes) / want) ** 4


def band(n: int) -> int:
    return min(BANDS - 1, int(math.log2(n / MIN_RUN) * 2))


def score_bin(x: float) -> int:
    return min(BINS - 1, int(x * BINS))


#: ordinary words of some languages, for decoys that do not depend on the table
_ORDINARY = """the of and to in that is was for with as on this from they which one would there their about other into more when people
house water morning between country because different number against government children important question nothing together
der die und nicht mit eine auch nach werden haben zwischen Zeit Stadt Wasser Regierung le les des une dans pour avec sur plus comme
tout entre temps ville maison el los las una por con para como pero todo desde tiempo ciudad casa gobierno il che non sono della anche
Monday London Europe January Internet University President System Research Company""".split()


@functools.cache
def reference() -> np.ndarray:
    """Histogram (bands x score bins) of runs of ordinary words, half of them with separators and numbers; always the same."""
    out = np.zeros((BANDS, BINS), np.int64)
    r = np.random.default_rng(8)
    for n in range(BANDS):
        low, high = math.ceil(MIN_RUN * 2 ** (n / 2)), math.ceil(MIN_RUN * 2 ** ((n + 1) / 2))
        for size in r.integers(low, high, REFERENCE).tolist():
            words = [w.capitalize() if up else w for w, up in zip(r.choice(_ORDINARY, size // 3 + 1).tolist(), (r.random(size // 3 + 1) < 0.1).tolist(), strict=True)]
            if r.random() < 0.5:  # names of files and pages: separators and numbers
                words = [str(r.integers(1, 2100)) if r.random() < 0.2 else w for w in words]
                letters = str(r.choice(["-", "_", "/"])).join(words)
            else:
                letters = "".join(words)
            while len(letters) < size:
                letters += letters
            out[n, score_bin(score(letters[:size].encode()))] += 1
    return out


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, end, kind number) in code points, by start and then kind."""
    out = [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if len(m.group(2)) >= MIN_ASSIGN]
    out += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text) if m.end() - m.start() >= MIN_ACCESS]
    out += [(m.start(), m.end(), 2) for m in re.finditer(r"[0-9a-f]+", text) if m.end() - m.start() >= MIN_HEX]
    return sorted(out, key=lambda x: (x[0], x[2]))


def slab_spans(s: tk.Slab) -> list[list[tuple[int, int, int]]]:
    """The base spans of each document, found from the few places where they can begin."""
    out: list[list[tuple[int, int, int]]] = [[] for _ in range(s.n)]
    flat, low = s.data.tobytes(), tk.LOWER[s.data].tobytes()
    hot: dict[int, set[int]] = {}
    for kind, source, words in ((0, low, _WORDS), (1, flat, (b"AKIA",))):
        for w in words:
            at = source.find(w)
            while at >= 0:
                hot.setdefault(int(np.searchsorted(s.off, at, side="right") - 1), set()).add(kind)
                at = source.find(w, at + 1)
    a, b = s.runs(_HEX)
    long = b - a >= MIN_HEX
    a, b = a[long], b[long]
    points = None
    if len(a) or hot:
        points = tk.code_points(s)
    for x, y, d in zip(a.tolist(), b.tolist(), s.doc_of(a).tolist(), strict=True):
        begin = points[s.off[d]]
        out[d].append((int(points[x] - begin), int(points[y] - begin), 2))
    for d, kinds in hot.items():
        text = s.text(d)
        if 0 in kinds:
            out[d] += [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if len(m.group(2)) >= MIN_ASSIGN]
        if 1 in kinds:
            out[d] += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text) if m.end() - m.start() >= MIN_ACCESS]
    for x in out:
        x.sort(key=lambda y: (y[0], y[2]))
    return out


_LETTERS = np.zeros(256, bool)
_LETTERS[[*range(65, 91), *range(97, 123)]] = True


class _Spans:
    """Spans in order of their starts, asked for those that touch a run."""

    def __init__(self, spans: list[tuple[int, int, int]]):
        self.spans, self.starts = spans, [x[0] for x in spans]
        self.reach = list(itertools.accumulate((x[1] for x in spans), max))

    def outside(self, p: int, q: int) -> tuple[list[tuple[int, int]], bool]:
        """(the parts of p..q outside the spans, whether the whole of p..q is to be scored); no parts if too little is left."""
        touching = [x for x in self.spans[bisect_right(self.reach, p) : bisect_left(self.starts, q)] if x[1] > p]
        pieces, at = [], p
        for u, v, _ in touching:
            if u > at:
                pieces.append((at, u))
            at = max(at, v)
        if at < q:
            pieces.append((at, q))
        if sum(v - u for u, v in pieces) >= MIN_RUN:
            return pieces, False
        return (pieces, True) if all(k == 2 for *_, k in touching) else ([], False)


#: digits of years and small numbers, in turn, where the neighbouring text has none
_NUMBERS = np.frombuffer(b"19982004101220163652471001975202330601280", np.uint8)
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True


def decoys_of(token: np.ndarray, letters: np.ndarray, digits: np.ndarray) -> Iterator[bytes]:
    """Up to ``DECOYS`` runs with the classes of characters of the token, its letters and digits replaced by the next ones of ordinary text."""
    alphabet = np.zeros(256, bool)
    alphabet[list(infer_encoding(token.tobytes())[1])] = True
    upper, lower, digit = (token >= 65) & (token <= 90), (token >= 97) & (token <= 122), _DIGIT[token]
    both = upper | lower
    low = letters | 32
    low = low[alphabet[low] | alphabet[low & 0xDF]]
    numbers = digits[alphabet[digits]]
    if len(numbers) < digit.sum():
        numbers = _NUMBERS[alphabet[_NUMBERS]]
    n, m = int(both.sum()), int(digit.sum())
    if n and len(low) < n:
        return
    for k in range(min(DECOYS, len(low) // n) if n else DECOYS if m else 0):
        out = token.copy()
        if n:
            out[both] = low[k * n : (k + 1) * n]
            out[upper] &= 0xDF
        if m:
            out[digit] = numbers[(7 * k + np.arange(m)) % len(numbers)]
        yield out.tobytes()


@tk.tidy
def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for i, j, s in tk.slabs(b.column(1)):
            spans = slab_spans(s)
            found: list[list[dict]] = [[] for _ in range(s.n)]
            decoys: list[list[int]] = [[] for _ in range(s.n)]
            a, e = s.runs(_RUN)
            keep = e - a >= MIN_RUN
            a, e = a[keep], e[keep]
            docs = s.doc_of(a)
            points = tk.code_points(s) if len(a) else None
            words = _LETTERS[s.data] | _DIGIT[s.data]  # letters and digits of words, without those of runs
            for x, y in zip(a.tolist(), e.tolist(), strict=True):
                words[x:y] = False
            beside: dict[int, _Spans] = {}
            for x, y, d in zip(a.tolist(), e.tolist(), docs.tolist(), strict=True):
                begin = int(points[s.off[d]])
                p, q = int(points[x]) - begin, int(points[y]) - begin
                if d not in beside:
                    beside = {d: _Spans(spans[d])}  # runs come document by document
                pieces, whole = beside[d].outside(p, q)
                if not pieces:
                    continue
                token = s.data[x:y]  # one byte a code point
                if not whole:
                    token = np.concatenate([token[u - p : v - p] for u, v in pieces])
                n, w = len(token), score(token.tobytes())
                found[d] += [{"start": u, "end": v, "band": band(n), "score": w} for u, v in pieces]
                u, v = max(x - 80 * n, int(s.off[d])), min(y + 80 * n, int(s.off[d + 1]))
                near = s.data[u:v][words[u:v]]
                decoys[d] += [band(n) * BINS + score_bin(score(t)) for t in decoys_of(token, near[_LETTERS[near]], near[_DIGIT[near]])]
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0).slice(i, j - i),
                    *(pa.array([sum(k == n for *_, k in x) for x in spans], pa.int64()) for n in range(3)),
                    pa.array([[{"start": p, "end": q, "kind": k} for p, q, k in x] for x in spans], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.int32())]))),
                    pa.array(found, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("band", pa.int32()), ("score", pa.float64())]))),
                    pa.array(decoys, pa.list_(pa.int32())),
                ],
                names=["doc_id", "n_assign", "n_access", "n_hex", "base", "runs", "decoys"],
            )


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base array<struct<start:long,end:long,kind:int>>, runs array<struct<start:long,end:long,band:int,score:double>>, decoys array<int>"


def thresholds(scanned: DataFrame, fdr: float) -> dict[int, float]:
    """For each band of lengths the least score that passes; bands without one are absent."""
    target = scanned.select(F.explode("runs").alias("r")).select((F.col("r.band") * BINS + F.least(F.lit(BINS - 1), F.floor(F.col("r.score") * BINS))).cast("int").alias("k"), F.lit(0).alias("decoy"))
    decoy = scanned.select(F.explode("decoys").alias("k"), F.lit(1).alias("decoy"))
    hist = np.zeros((2, BANDS * BINS), np.int64)
    for r in target.unionByName(decoy).groupBy("decoy", "k").count().collect():  # 2 x bands x BINS rows at most
        hist[r["decoy"], r["k"]] = r["count"]
    runs, decoys = hist.reshape(2, BANDS, BINS)
    if not runs.any():
        return {}
    decoys = decoys + reference()
    p = np.empty((BANDS, BINS))
    for n in range(BANDS):
        pool = decoys[max(0, n - 1) : n + 2].sum(0)
        p[n] = (1 + pool[::-1].cumsum()[::-1]) / (1 + pool.sum())
    p[:, 0] = 1.0  # plainly not random
    order = np.sort(np.unique(p))
    below = np.array([runs[p <= x].sum() for x in order])
    ok = order[(below > 0) & (order * runs.sum() <= fdr * below)]
    return {n: int(np.flatnonzero(p[n] <= ok[-1])[0]) / BINS for n in range(BANDS) if len(ok) and (p[n] <= ok[-1]).any()}


def scan(docs: DataFrame, text: str = "text", fdr: float = 0.05) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base (spans of the fixed patterns), extra (spans that the tests add)."""
    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs[text].cast("string").alias("text"))
    scanned = shared.keep(src.mapInArrow(_scan, SCHEMA), "secrets")
    least = thresholds(scanned, fdr)
    passes = lambda r: F.lit(False) if not least else F.coalesce(F.element_at(F.create_map(*(F.lit(x) for kv in least.items() for x in kv)), r["band"]) <= r["score"], F.lit(False))
    extra = F.transform(F.filter("runs", passes), lambda r: F.struct(r["start"].alias("start"), r["end"].alias("end"), F.lit(3).alias("kind")))
    return scanned.select("doc_id", "n_assign", "n_access", "n_hex", "base", extra.alias("extra"))


def _joined(spans):
    kind = F.create_map(*(F.lit(x) for i, k in enumerate((*KINDS, "random")) for x in (i, k)))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(kind, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def digests(scanned: DataFrame) -> DataFrame:
    every = F.array_sort(F.transform(F.concat("base", "extra"), lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end"))))
    return scanned.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(every).alias("spans"))


MARK = "[REDACTED]"


def redact(docs: DataFrame, fdr: float = 0.05) -> DataFrame:
    """docs with every span, of the fixed patterns and of the tests, replaced by a mark; n_chars, if there, follows. Null text stays null."""
    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    scanned = shared.keep(src.mapInArrow(_scan, SCHEMA).select("runs", "decoys").where("size(runs) > 0 or size(decoys) > 0"), "secrets")
    least = thresholds(scanned, fdr)
    names = docs.columns
    at, size_at = names.index("text"), names.index("n_chars") if "n_chars" in names else None

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = []
            plain = b.select([at]).rename_columns(["text"])
            for x in _scan([pa.RecordBatch.from_arrays([pa.nulls(b.num_rows, pa.int64()), plain.column(0)], names=["doc_id", "text"])]):
                base, runs = x.column("base").to_pylist(), x.column("runs").to_pylist()
                found += [[(y["start"], y["end"]) for y in p] + [(y["start"], y["end"]) for y in q if y["score"] >= least.get(y["band"], 2.0)] for p, q in zip(base, runs, strict=True)]
            if not any(found):
                yield b
                continue
            text = plain.column(0).to_pylist()
            sizes = None if size_at is None else b.column(size_at).to_pylist()
            for k, spans in enumerate(found):
                if spans:
                    out, done, t = [], 0, text[k]
                    for p, q in sorted(spans):
                        if p >= done:
                            out += [t[done:p], MARK]
                        done = max(done, q)
                    text[k] = "".join(out) + t[done:]
                    if sizes is not None and sizes[k] is not None:
                        sizes[k] = len(text[k])
            columns = list(b.columns)
            columns[at] = pa.array(text, b.schema.field(at).type)
            if sizes is not None:
                columns[size_at] = pa.array(sizes, b.schema.field(size_at).type)
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.mapInArrow(run, docs.schema)
