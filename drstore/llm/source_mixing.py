"""Mixing to target weights by soft domain membership.

A softmax classifier, fitted on labelled documents, gives every document posterior probabilities of the domains (here the four pairs of
quality and toxicity labels). A document with ``t`` tokens and posteriors ``p`` brings ``t p`` expected tokens to the domains at rate 1. The rates
``r >= 0`` minimise the squared gaps between the expected domain totals and their targets, each over its target, by
projected gradient from ``r = 1``: in the metric where a document weighs its tokens, a step is
``r <- max(0, r - step * sum_d p_d gap_d / target_d)``. Momentum speeds it up. The totals are one distributed sum in each step;
since a step depends only on the document and on one short vector of gaps, tasks replay the earlier steps instead of
keeping state, so a lost task costs nothing but itself.

The end is the optimum, not a lack of progress: totals within ``tolerance`` of the targets, or rates that a projected step of length one moves by
at most ``STILL`` in every document (the optimality condition, also where no rates reach the targets). Where such steps get slow, backward steps
follow: the gap is that of the totals after the step, found by Newton's method on one number a domain, so that a step can be
of any length. They are replayed like the others. If the bounds on steps are hit, a warning says so and gives the totals.

``copies`` rounds a rate to whole copies so that its expectation is the rate (by a hash of doc_id and the text).

The classifier sees at most ``max_labelled`` labelled rows; everything else covers all rows. Null text is empty, has no tokens and keeps rate
1. A document without any label in a class keeps prior posteriors; without labels there is one domain and all rates are
total/total = 1. Null doc_id and repeated rows are rows like others. An empty table gives an empty result.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import hashed_linear as hl
from . import shared
from . import textkit as tk

#: (quality, toxic) of each domain, and the share of tokens that it shall have
DOMAINS = ((1, 0), (0, 0), (1, 1), (0, 1))
TARGETS = (0.90, 0.07, 0.02, 0.01)
#: the most that a projected step may still move a rate at the optimum
STILL = 1e-4
BACKWARD_STEPS, NEWTON_STEPS = 24, 40
_HALVINGS = 0.5 ** np.arange(12)


def classifier(docs: DataFrame, labels: DataFrame, max_labelled: int = 8000) -> hl.Scorer | None:
    lab = labels.select(labels["doc_id"].cast("long").alias("doc_id"), labels["quality"].cast("int").alias("q"), labels["toxic"].cast("int").alias("t")).where("doc_id is not null and q is not null and t is not null")
    lab = lab.orderBy(F.xxhash64("doc_id"), "doc_id", "q", "t").limit(max_labelled)  # a bounded sample, small enough to send
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text")).join(F.broadcast(lab), "doc_id")
    rows = rows.select("text", *(((F.col("q") == q) & (F.col("t") == t)).cast("double").alias(f"d{k}") for k, (q, t) in enumerate(DOMAINS)))
    cuts, number, target = hl.sample_features(rows, [f"d{k}" for k in range(len(DOMAINS))], 4 * max_labelled)
    keep = target.sum(1) > 0 if len(target) else np.zeros(0, bool)
    if not keep.any():
        return None
    return hl.train(cuts, number, np.where(keep[:, None], target, 1 / len(DOMAINS)))


def posteriors(docs: DataFrame, scorer: hl.Scorer | None, domains: int) -> DataFrame:
    """doc_id, tie (hash of the text), tokens, p0 ... of each document."""
    sent = docs.sparkSession.sparkContext.broadcast(scorer)  # N_FEATURES x domains numbers, whatever the corpus

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, s, low in hl.both_slabs(b.column(1)):
                cuts, number, counts = hl.features(s, low)
                p = sent.value.probabilities(cuts, number) if sent.value is not None else np.full((s.n, domains), 1 / domains)
                tie = s.hash(s.off[:-1], s.off[1:]).view(np.int64)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array(tie), pa.array(counts["n_words"].astype(np.int64)), *(pa.array(p[:, k]) for k in range(domains))], names=["doc_id", "tie", "tokens", *(f"p{k}" for k in range(domains))])

    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id long, tie long, tokens long, " + ", ".join(f"p{k} double" for k in range(domains)))


def replay(p: np.ndarray, steps: list[tuple[np.ndarray, float]], most: float = np.inf) -> tuple[np.ndarray, np.ndarray]:
    """(rates, extrapolated rates) of documents with posteriors p after some steps of (scaled gap, momentum)."""
    r = np.ones(len(p))
    y = r
    for gap, momentum in steps:
        new = np.clip(y - p @ gap, 0.0, most)
        y = np.clip(new + momentum * (new - r), 0.0, most)
        r = new
    return r, y


def solve(table: DataFrame, targets: Sequence[float], max_steps: int = 80, tolerance: float = 1e-4, most: float = np.inf) -> tuple[list[tuple[np.ndarray, float]], np.ndarray, np.ndarray]:
    """The steps taken, the target totals and the totals that they reach."""
    d = len(targets)
    names = [f"p{k}" for k in range(d)]
    share = np.asarray(targets, float) / sum(targets)
    start = np.array(table.agg(*(F.sum(F.col(n) * F.col("tokens")).alias(n) for n in names)).first(), dtype=object)
    total = np.array([float(x or 0) for x in start])
    if total.sum() == 0:
        return [], total, total
    goal = share * total.sum()
    # the largest curvature in this metric: largest eigenvalue of sum t p p' / goal
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    gram = table.agg(*(F.sum(F.col("tokens") * F.col(f"p{i}") * F.col(f"p{j}")).alias(f"g{i}_{j}") for i, j in pairs)).first()
    m = np.zeros((d, d))
    for i, j in pairs:
        m[i, j] = m[j, i] = gram[f"g{i}_{j}"]
    root = 1 / np.sqrt(np.maximum(goal, 1e-9))
    step = 1 / max(np.linalg.eigvalsh(m * root[:, None] * root[None, :]).max(), 1e-12)

    def sums(steps: list[tuple[np.ndarray, float]]) -> tuple[np.ndarray, np.ndarray]:
        @tk.tidy
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            a, c = np.zeros(d), np.zeros(d)
            for b in batches:
                t = b.column(0).to_numpy().astype(float)
                p = np.column_stack([b.column(k + 1).to_numpy() for k in range(d)])
                r, y = replay(p, steps, most)
                a += (t * r) @ p
                c += (t * y) @ p
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(d)), pa.array(a), pa.array(c)], names=["k", "r", "y"])

        got = table.select("tokens", *names).mapInArrow(run, "k long, r double, y double").groupBy("k").agg(F.sum("r").alias("r"), F.sum("y").alias("y")).collect()
        a, c = np.zeros(d), np.zeros(d)
        for x in got:
            a[x["k"]], c[x["k"]] = x["r"], x["y"]
        return a, c

    def backward(steps: list[tuple[np.ndarray, float]], rise: np.ndarray, tries: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray, float, float]]:
        """For each vector v: totals at clip(r - p v), their slope (d x d), the sum of the clip's integral, and how far a projected step along p rise moves a rate at r."""

        @tk.tidy
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            got, moved = np.zeros((len(tries), d + d * d + 1)), 0.0
            for b in batches:
                t = b.column(0).to_numpy().astype(float)
                p = np.column_stack([b.column(k + 1).to_numpy() for k in range(d)])
                p, t = p[t > 0], t[t > 0]
                r = replay(p, steps, most)[0]
                if len(r):
                    moved = max(moved, float(np.abs(r - np.clip(r - p @ rise, 0.0, most)).max()))
                for i, v in enumerate(tries):
                    z = r - p @ v
                    new = np.clip(z, 0.0, most)
                    free = p[(z > 0) & (z < most)]
                    got[i, :d] += (t * new) @ p
                    got[i, d:-1] += ((t[(z > 0) & (z < most)])[:, None] * free).T.dot(free).ravel()
                    got[i, -1] += float((t * new * (z - new / 2)).sum())
            flat = got.ravel()
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat) + 1)), pa.array(np.append(flat, 0.0)), pa.array(np.append(np.zeros(len(flat)), moved))], names=["k", "x", "moved"])

        rows = table.select("tokens", *names).mapInArrow(run, "k long, x double, moved double").groupBy("k").agg(F.sum("x").alias("x"), F.max("moved").alias("moved")).collect()
        flat = np.zeros(len(tries) * (d + d * d + 1))
        for x in rows:
            if x["k"] < len(flat):
                flat[x["k"]] = x["x"]
        moved = max((x["moved"] for x in rows), default=0.0)
        return [(x[:d], x[d:-1].reshape(d, d), float(x[-1]), moved) for x in flat.reshape(len(tries), -1)]

    floor = np.maximum(goal, 1e-9)
    steps: list[tuple[np.ndarray, float]] = []
    at_r = at_y = total
    least, idle, k = np.inf, 0, 0
    while len(steps) < max_steps:
        gap = (at_y - goal) / floor
        off = (at_r - goal) / floor
        cost = float((off * off * goal).sum() / goal.sum())
        if np.abs(off).max() < tolerance:
            return steps, goal, at_r
        idle = 0 if cost < 0.995 * least else idle + 1
        if idle >= 6:  # slow, or near the optimum
            break
        k = 0 if cost > least else k + 1  # momentum starts anew when the cost rises
        least = min(least, cost)
        steps.append((step * gap, k / (k + 3)))
        at_r, at_y = sums(steps)

    if steps:  # from here on without momentum
        steps[-1] = (steps[-1][0], 0.0)
    length, moved = 16 * step, np.inf
    for _ in range(BACKWARD_STEPS):
        off = (at_r - goal) / floor
        if np.abs(off).max() < tolerance:
            return steps, goal, at_r
        u = off  # the gap after the step; Newton's method on floor u + goal - totals(clip(r - length p u)) = 0, the slope of a convex function
        (at, slope, area, moved), *_ = backward(steps, off, [length * u])
        if moved <= STILL:
            return steps, goal, at_r
        value = float((floor * u * u / 2 + goal * u).sum() + area / length)
        for _ in range(NEWTON_STEPS):
            short = floor * u + goal - at
            if np.abs(short / floor).max() < tolerance / 10:
                break
            way = np.linalg.solve(np.diag(floor) + length * slope, short)
            tries = [u - h * way for h in _HALVINGS]
            found = backward(steps, off, [length * x for x in tries])
            values = [float((floor * x * x / 2 + goal * x).sum() + f[2] / length) for x, f in zip(tries, found, strict=True)]
            best = int(np.argmin(values))
            if values[best] > value:
                break  # no digit left to gain
            value, u, (at, slope, *_) = values[best], tries[best], found[best]
        steps.append((length * u, 0.0))
        at_r = at
        length *= 8
    off = (at_r - goal) / floor
    if np.abs(off).max() >= tolerance:
        moved = backward(steps, off, [off])[0][3]
        if moved > STILL:
            warnings.warn(f"rates are not at their optimum: a projected step still moves one by {moved:.2g}; totals {at_r.tolist()}, targets {goal.tolist()}", RuntimeWarning, stacklevel=2)
    return steps, goal, at_r


def _copies(rate: np.ndarray, ident: pa.Array, tie: np.ndarray) -> np.ndarray:
    known = ident.cast(pa.int64()).fill_null(0).to_numpy().astype(np.uint64)
    u = (tk.mix(tk.mix(known) ^ tie) >> np.uint64(11)).astype(float) / 2.0**53
    return np.floor(rate + u).astype(np.int64)


def rates(table: DataFrame, steps: list[tuple[np.ndarray, float]], domains: int, most: float = np.inf) -> DataFrame:
    """Adds rate and copies."""
    names = table.columns

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            p = np.column_stack([b.column(names.index(f"p{k}")).to_numpy() for k in range(domains)])
            r = np.where(b.column(names.index("tokens")).to_numpy() > 0, replay(p, steps, most)[0], 1.0)
            copies = _copies(r, b.column(names.index("doc_id")), b.column(names.index("tie")).to_numpy().view(np.uint64))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(r), pa.array(copies)], names=[*names, "rate", "copies"])

    return table.mapInArrow(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in table.schema) + ", rate double, copies long")


def _solved(docs: DataFrame, labels: DataFrame, targets: Sequence[float], max_labelled: int, most: float) -> tuple[hl.Scorer | None, DataFrame, list[tuple[np.ndarray, float]]]:
    scorer = classifier(docs, labels, max_labelled)
    table = shared.keep(posteriors(docs, scorer, len(targets)), "posteriors")
    return scorer, table, solve(table, targets, most=most)[0]


def mix(docs: DataFrame, labels: DataFrame, targets: Sequence[float] = TARGETS, max_labelled: int = 8000, most: float = np.inf) -> DataFrame:
    """doc_id, tie, tokens, p0.., rate, copies. ``most``: an upper bound of the rates."""
    _, table, steps = _solved(docs, labels, targets, max_labelled, most)
    return rates(table, steps, len(targets), most)


def resample(docs: DataFrame, labels: DataFrame, targets: Sequence[float] = TARGETS, max_labelled: int = 8000, most: float = np.inf) -> DataFrame:
    """The rows of docs, with all their columns, each as often as its copies say."""
    scorer, _, steps = _solved(docs, labels, targets, max_labelled, most)
    sent = docs.sparkSession.sparkContext.broadcast(scorer)
    names = docs.columns
    at, ident, domains = names.index("text"), names.index("doc_id"), len(targets)

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, s, low in hl.both_slabs(b.column(at).cast(pa.string())):
                cuts, number, counts = hl.features(s, low)
                p = sent.value.probabilities(cuts, number) if sent.value is not None else np.full((s.n, domains), 1 / domains)
                r = np.where(counts["n_words"] > 0, replay(p, steps, most)[0], 1.0)
                c = _copies(r, b.column(ident).slice(i, j - i), s.hash(s.off[:-1], s.off[1:]))
                part = b.slice(i, j - i)
                yield part.take(pa.array(np.repeat(np.arange(s.n), c)))

    return docs.mapInArrow(run, docs.schema)
