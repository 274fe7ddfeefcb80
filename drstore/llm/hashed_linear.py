"""Hashed text features and a softmax scorer over them.

Features of a document: which of ``2^BITS`` buckets its lower-case words fall into, and one of ``STAT_BINS`` bins of each ratio of
``quality_rules``. Training runs on the driver over a bounded sample; prediction is a sum of bucket weights.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import quality_rules
from . import textkit as tk

BITS, STAT_BINS = 16, 12
N_WORD = 1 << BITS
#: upper ends of the bins of each ratio
_EDGES = {
    "words": np.array([1, 5, 10, 20, 40, 80, 160, 320, 640, 1280, 5000]),
    "mean_word_chars": np.array([1.5, 2, 2.5, 3, 4, 5, 6, 7, 8, 10, 15]),
}
_SHARE_EDGES = np.array([0.001, 0.01, 0.03, 0.06, 0.1, 0.2, 0.3, 0.45, 0.6, 0.8, 0.95])
N_FEATURES = N_WORD + STAT_BINS * len(quality_rules.RATIOS)


def features(s: tk.Slab, low: tk.Slab) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray]]:
    """(n+1 cuts, feature numbers, counts): the distinct features of each document. ``low`` is the slab with lower-case hashes."""
    start, end = low.words()
    cuts = low.per_doc(start)
    bucket = (low.hash(start, end) >> np.uint64(64 - BITS)).astype(np.int64)
    doc = np.repeat(np.arange(s.n), np.diff(cuts))
    key = np.unique(doc * N_WORD + bucket)
    counts = quality_rules.slab_counts(s)
    stats = []
    for k, (name, v) in enumerate(quality_rules._ratio_arrays(counts).items()):
        stats.append(np.arange(s.n) * N_FEATURES + N_WORD + k * STAT_BINS + np.searchsorted(_EDGES.get(name, _SHARE_EDGES), v, side="right"))
    both = np.sort(np.concatenate([key // N_WORD * N_FEATURES + key % N_WORD, *stats]))
    owner, number = both // N_FEATURES, both % N_FEATURES
    return np.searchsorted(owner, np.arange(s.n + 1)), number, counts


def both_slabs(column: pa.Array) -> Iterator[tuple[int, int, tk.Slab, tk.Slab]]:
    for i, j, s in tk.slabs(column):
        yield i, j, s, tk.Slab(s.data, s.off, lower=True)


@dataclass
class Scorer:
    weight: np.ndarray  # (N_FEATURES, classes)
    bias: np.ndarray

    def logits(self, cuts: np.ndarray, number: np.ndarray) -> np.ndarray:
        w = self.weight[number]
        run = np.zeros((len(w) + 1, w.shape[1]))
        np.cumsum(w, axis=0, dtype=float, out=run[1:])
        return run[cuts[1:]] - run[cuts[:-1]] + self.bias

    def probabilities(self, cuts: np.ndarray, number: np.ndarray) -> np.ndarray:
        z = self.logits(cuts, number)
        z = np.exp(z - z.max(1, keepdims=True))
        return z / z.sum(1, keepdims=True)


def train(cuts: np.ndarray, number: np.ndarray, target: np.ndarray, epochs: int = 60, rate: float | np.ndarray = 0.3, ridge: float = 1e-4, size: int = N_FEATURES, weight: np.ndarray | None = None) -> Scorer:
    """target: (rows, classes) label distributions; features are numbered below ``size``; ``weight``: how many rows each row stands for; ``rate``: of steps, for all features or each. Adaptive gradient steps over the whole sample."""
    n, classes = target.shape
    row = np.repeat(np.arange(n), np.diff(cuts))
    part = np.full(n, 1 / max(n, 1)) if weight is None else weight / max(weight.sum(), 1e-12)
    model = Scorer(np.zeros((size, classes), np.float32), np.log(part @ target + 1e-6) if n else np.zeros(classes))
    seen = np.zeros_like(model.weight)
    seen_bias = np.zeros(classes)
    for _ in range(epochs if n else 0):
        err = (model.probabilities(cuts, number) - target) * part[:, None]
        for c in range(classes):
            g = np.bincount(number, err[row, c], minlength=size).astype(np.float32) + np.float32(ridge / n) * model.weight[:, c]
            seen[:, c] += g * g
            model.weight[:, c] -= rate * g / np.sqrt(seen[:, c] + 1e-12)
        g = err.sum(0)
        seen_bias += g * g
        model.bias = model.bias - np.max(rate) * g / np.sqrt(seen_bias + 1e-12)
    return model


def with_votes(cuts: np.ndarray, number: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Features of documents and, behind them, one for each labeller's vote (-1, 0 or 1)."""
    k = v.shape[1]
    more = N_FEATURES + 3 * np.arange(k) + v + 1
    return cuts + k * np.arange(len(cuts)), np.insert(number, np.repeat(cuts[1:], k), more.ravel())


def as_lists(cuts: np.ndarray, number: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(number.astype(np.int32)))


def collected(table: pa.Table, names: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(cuts, numbers, targets) of collected rows with a list f and numeric columns."""
    f = table["f"].combine_chunks()
    if isinstance(f, pa.ChunkedArray):
        f = pa.concat_arrays(f.chunks) if f.num_chunks else pa.array([], pa.list_(pa.int32()))
    cuts = np.concatenate([[0], np.cumsum(f.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64) if len(f) else np.zeros(1, np.int64)
    return cuts, f.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.column_stack([table[c].to_numpy() for c in names]) if names else np.zeros((len(f), 0))


def sample_features(rows: DataFrame, target_columns: list[str], most: int = 100_000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Driver-side (cuts, numbers, targets) of a bounded sample: rows has text and numeric target columns; at most ``most`` rows, however often an id is repeated."""
    names = target_columns

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, s, low in both_slabs(b.column(0)):
                cuts, number, _ = features(s, low)
                yield pa.RecordBatch.from_arrays([as_lists(cuts, number), *(b.column(k + 1).slice(i, j - i) for k in range(len(names)))], names=["f", *names])

    got = rows.select(rows["text"].cast("string").alias("text"), *(rows[c].cast("double").alias(c) for c in names)).mapInArrow(run, "f array<int>, " + ", ".join(f"{c} double" for c in names)).limit(most).toArrow()
    return collected(got, names)
