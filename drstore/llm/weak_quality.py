"""Quality classifier from weak labels.

Heuristic labellers vote bad (1), good (-1) or nothing (0) on each document: seven on text statistics, and - for toxicity - ``LISTS`` lists of word stems (the
first ``STEM`` characters of a word). A stem is on a list if it is more frequent in documents labelled toxic than chance allows; every stem is on one
list only, so within a class the lists say different things. For each of the two questions
expectation-maximisation fits class shares and every labeller's vote probabilities in each class to the counts of vote
patterns (a table of fixed size), without looking at labels. The posterior labels of a bounded sample, half of it documents that they accuse, then train a hashed
linear scorer over the words, the statistics and the votes.

The scorer gives the verdict: ``p_bad`` and ``p_toxic`` are its probabilities, ``kept`` needs both under a half; the posteriors are returned beside them. Null or empty
text gets the votes of an empty document, a very long one is read whole. Without labels there are no stems and p_toxic is 0. Repeated rows and ties give repeated results, null
doc_id is carried.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import hashed_linear as hl
from . import quality_rules
from . import textkit as tk

#: labeller -> (statistic, bad at or above, bad at or below, good between)
LABELLERS = {
    "symbols": ("symbols_per_word", 0.3, None, (0.0, 0.05)),
    "repeats": ("repeated_word_share", 0.3, None, (0.0, 0.1)),
    "capitals": ("upper_share", 0.5, None, (0.0, 0.2)),
    "bangs": ("bangs_per_word", 0.4, None, (0.0, 0.1)),
    "variety": ("distinct_word_share", None, 0.2, (0.35, 1.0)),
    "length": ("words", None, 4, (12, 1e18)),
    "word_length": ("mean_word_chars", 15.0, 1.5, (2.5, 12.0)),
}
#: labellers over stems, and characters of a stem
LISTS, STEM = 5, 6


def votes(counts: dict[str, np.ndarray]) -> np.ndarray:
    """(documents, labellers) of -1, 0, 1."""
    x = quality_rules._ratio_arrays(counts)
    out = []
    for stat, above, below, (lo, hi) in LABELLERS.values():
        v = x[stat]
        bad = (v >= above if above is not None else np.zeros(len(v), bool)) | (v <= below if below is not None else np.zeros(len(v), bool))
        out.append(np.where(bad, 1, np.where((v >= lo) & (v <= hi), -1, 0)))
    return np.column_stack(out)


def pattern(v: np.ndarray) -> np.ndarray:
    """One number for each row of votes."""
    return ((v + 1) * 3 ** np.arange(v.shape[1])).sum(1).astype(np.int64)


def unpattern(k: np.ndarray, labellers: int) -> np.ndarray:
    return np.asarray(k, np.int64)[:, None] // 3 ** np.arange(labellers) % 3 - 1


#: What a labeller is expected to say (good, nothing, bad), before any data: of good documents, of faulty ones, and
#: of documents with the fault that it is made for.
OF_GOOD, OF_FAULTY, OF_ITS_FAULT = np.array([[0.9, 0.09, 0.01], [0.7, 0.1, 0.2], [0.1, 0.1, 0.8]])


@dataclass
class LabelModel:
    """Class 0 is good, the others are kinds of fault."""

    share: np.ndarray
    table: np.ndarray  # (class, labeller, vote + 1)

    def classes(self, v: np.ndarray) -> np.ndarray:
        z = np.tile(np.log(self.share), (len(v), 1))
        for j in range(v.shape[1]):
            z += np.log(self.table[:, j, :]).T[v[:, j] + 1]
        z = np.exp(z - z.max(1, keepdims=True))
        return z / z.sum(1, keepdims=True)

    def posterior(self, v: np.ndarray) -> np.ndarray:
        return 1 - self.classes(v)[:, 0]


def expectation_maximisation(v: np.ndarray, n: np.ndarray, kinds: bool, rounds: int = 200, trust: float = 0.05, max_false: float = 0.01) -> LabelModel:
    """v: distinct vote rows; n: how many documents have each. ``kinds``: one class of faulty documents for each labeller, else one.

    Labellers are independent within a class. Since a faulty document need not have several faults, a single bad class would fit only the
    kind that most labellers share; so each labeller starts a class of its own. ``max_false`` bounds how often a labeller
    accuses good documents, ``trust`` is the weight of the prior as a share of a class.
    """
    v = np.asarray(v)
    labellers = v.shape[1]
    prior = np.stack([np.tile(OF_GOOD, (labellers, 1)), *([np.tile(OF_FAULTY, (labellers, 1))] * (labellers if kinds else 1))])
    if kinds:
        prior[1 + np.arange(labellers), np.arange(labellers)] = OF_ITS_FAULT
    else:
        prior[1, :] = OF_ITS_FAULT
    classes = len(prior)
    share = np.full(classes, 0.1 / (classes - 1))
    share[0] = 0.9
    model = LabelModel(share, prior)
    q = model.classes(v)
    for _ in range(rounds):
        w = q * n[:, None]
        share = np.clip(w.sum(0) / max(n.sum(), 1), 1e-5, 1)
        table = prior * (trust * w.sum(0)[:, None, None] + 1)
        for j in range(labellers):
            for k in range(classes):
                table[k, j] += np.bincount(v[:, j] + 1, w[:, k], minlength=3)
        table /= table.sum(2, keepdims=True)
        over = np.maximum(table[0, :, 2] - max_false, 0)
        table[0, :, 2] -= over
        table[0, :, 0] += over
        model = LabelModel(share / share.sum(), table)
        new = model.classes(v)
        done = np.abs(new - q).max() < 1e-6 if len(v) else True
        q = new
        if done:
            break
    return model


def stem_lists(docs: DataFrame, labels: DataFrame, max_labelled: int = 20_000, chance: float = 1e-6, ratio: float = 15.0) -> np.ndarray:
    """Hashes of stems that mark toxic documents, the most frequent first, by document frequency in labelled rows.

    A stem counts if documents with it are toxic more often than ``chance`` allows (the binomial tail if it had nothing to do with toxicity) and it is ``ratio``
    times as frequent in toxic ones. They are found among at most ``max_labelled`` labels, so their number has a bound too.
    """
    lab = labels.select(labels["doc_id"].cast("long").alias("doc_id"), labels["toxic"].cast("int").alias("toxic")).where("doc_id is not null and toxic is not null")
    lab = lab.orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(max_labelled)
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text")).join(F.broadcast(lab), "doc_id").select("toxic", "text")
    size = {r["toxic"]: r["count"] for r in lab.groupBy("toxic").count().collect()}
    if len(size) < 2:
        return np.empty(0, np.uint64)

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            toxic = b.column(0).to_numpy().astype(np.int64)
            for i, _, s in tk.slabs(b.column(1), lower=True):
                h, doc = stems(s)
                one = np.unique(np.stack([h, doc.astype(np.uint64)]), axis=1) if len(h) else np.empty((2, 0), np.uint64)
                bad = toxic[i + one[1].astype(np.int64)] > 0
                u, inverse = np.unique(one[0], return_inverse=True)
                yield pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(np.bincount(inverse, bad, len(u)).astype(np.int64)), pa.array(np.bincount(inverse, ~bad, len(u)).astype(np.int64))], names=["h", "bad", "good"])

    n_bad, n_good = sum(v for k, v in size.items() if k), size.get(0, 0)
    got = rows.mapInArrow(run, "h long, bad long, good long").groupBy("h").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    lift = (F.col("bad") / n_bad) / ((F.col("good") + 0.5) / max(n_good, 1))
    # stems that could pass: their toxic documents alone would have to be this unlikely
    least = math.ceil(math.log(chance) / math.log(max(n_bad / (n_bad + n_good), 1e-9)))
    rows = got.where((F.col("bad") >= least) & (lift >= ratio)).orderBy(F.desc("bad"), "h").collect()
    return np.array([r["h"] for r in rows if binomial_tail(r["bad"], r["bad"] + r["good"], n_bad / (n_bad + n_good)) < chance], np.int64).view(np.uint64)


def binomial_tail(k: int, n: int, p: float) -> float:
    """Probability of k or more of n."""
    return sum(math.exp(math.lgamma(n + 1) - math.lgamma(j + 1) - math.lgamma(n - j + 1) + j * math.log(p) + (n - j) * math.log1p(-p)) for j in range(k, n + 1))


_EDGE = np.zeros(256, bool)
_EDGE[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True


def stems(s: tk.Slab) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the first ``STEM`` characters of words without ASCII punctuation, and their documents."""
    a, b = s.runs(tk.WORD_BYTE & ~_EDGE)
    lead = np.flatnonzero(tk.LEAD_BYTE[s.data])
    after = np.searchsorted(lead, a) + STEM
    end = np.append(lead, len(s.data))[np.minimum(after, len(lead))]
    return s.hash(a, np.minimum(b, end)), s.doc_of(a)


def list_votes(s: tk.Slab, words: np.ndarray) -> np.ndarray:
    """(documents, LISTS) of -1 and 1; the stem that is k-th in frequency is on list k mod LISTS."""
    out = np.full((s.n, LISTS), -1)
    if len(words):
        order = np.argsort(words)
        h, doc = stems(s)
        at = np.minimum(np.searchsorted(words, h, sorter=order), len(words) - 1)
        hit = words[order[at]] == h
        out[doc[hit], order[at[hit]] % LISTS] = 1
    return out


N_HEURISTIC = len(LABELLERS)


def _patterns(words: np.ndarray):
    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, s in tk.slabs(b.column(1)):
                low = tk.Slab(s.data, s.off, lower=True)
                k = pattern(np.column_stack([votes(quality_rules.slab_counts(s)), list_votes(low, words)]))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array(k)], names=["doc_id", "pattern"])

    return run


@dataclass
class Classifier:
    words: np.ndarray
    quality: LabelModel
    toxic: LabelModel
    quality_scorer: hl.Scorer
    toxic_scorer: hl.Scorer

    def posteriors(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        toxic = self.toxic.posterior(v[:, N_HEURISTIC:]) if len(self.words) else np.zeros(len(v))
        return self.quality.posterior(v[:, :N_HEURISTIC]), toxic

    def votes(self, counts: dict[str, np.ndarray], low: tk.Slab) -> np.ndarray:
        return np.column_stack([votes(counts), list_votes(low, self.words)])


N_VOTES = 3 * (N_HEURISTIC + LISTS)


def fit(docs: DataFrame, labels: DataFrame, max_labelled: int = 20_000, max_sample: int = 6000) -> Classifier:
    words = stem_lists(docs, labels, max_labelled)
    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    got = src.mapInArrow(_patterns(words), "doc_id long, pattern long").groupBy("pattern").count().collect()  # 3^12 rows at most
    v = unpattern(np.array([r["pattern"] for r in got], np.int64), N_HEURISTIC + LISTS) if got else np.zeros((0, N_HEURISTIC + LISTS), int)
    n = np.array([r["count"] for r in got], float)
    quality = expectation_maximisation(v[:, :N_HEURISTIC], n, kinds=True)
    toxic = expectation_maximisation(v[:, N_HEURISTIC:], n, kinds=True, trust=0.02, max_false=0.001)
    model = Classifier(words, quality, toxic, None, None)
    accused = np.maximum(*model.posteriors(v)) > 0.5
    share = [min(1.0, max_sample / 2 / max(n[accused == x].sum(), 1)) for x in (False, True)]
    drawn = F.pmod(F.xxhash64("doc_id", "text", F.lit(9)), F.lit(1 << 30)) / float(1 << 30)

    @tk.tidy
    def sampled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, s, low in hl.both_slabs(b.column(0)):
                cuts, number, counts = hl.features(s, low)
                vote = model.votes(counts, low)
                bad, tox = model.posteriors(vote)
                rate = np.where(np.maximum(bad, tox) > 0.5, share[1], share[0])
                pick = pa.array(b.column(1).slice(i, j - i).to_numpy() < rate)
                lists = hl.as_lists(*hl.with_votes(cuts, number, vote))
                yield pa.RecordBatch.from_arrays([x.filter(pick) for x in (lists, pa.array(bad), pa.array(tox), pa.array(1 / rate))], names=["f", "bad", "tox", "weight"])

    # equal rows are drawn together, so the number has a bound of its own
    rows = src.select("text", drawn.alias("u")).where(F.col("u") < max(share)).mapInArrow(sampled, "f array<int>, bad double, tox double, weight double").limit(4 * max_sample)
    cuts, number, y = hl.collected(rows.toArrow(), ["bad", "tox", "weight"])
    two = lambda p: np.column_stack([1 - p, p])
    # a word is seen in few documents of the sample and learns in smaller steps than statistics and votes
    rate = np.where(np.arange(hl.N_FEATURES + N_VOTES) < hl.N_WORD, 0.1, 0.2).astype(np.float32)
    scorer = lambda p: hl.train(cuts, number, two(p), 60, rate, size=hl.N_FEATURES + N_VOTES, weight=y[:, 2])
    model.quality_scorer, model.toxic_scorer = scorer(y[:, 0]), scorer(y[:, 1])
    return model


def classify(docs: DataFrame, model: Classifier) -> DataFrame:
    """doc_id, p_bad, p_toxic, posterior_bad, posterior_toxic, kept."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # its size does not depend on the corpus

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in batches:
            for i, j, s, low in hl.both_slabs(b.column(1)):
                cuts, number, counts = hl.features(s, low)
                vote = m.votes(counts, low)
                bad, tox = m.posteriors(vote)
                cuts, number = hl.with_votes(cuts, number, vote)
                pb = m.quality_scorer.probabilities(cuts, number)[:, 1]
                pt = m.toxic_scorer.probabilities(cuts, number)[:, 1] if len(m.words) else np.zeros(s.n)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), *(pa.array(x) for x in (pb, pt, bad, tox)), pa.array((pb < 0.5) & (pt < 0.5))], names=["doc_id", "p_bad", "p_toxic", "posterior_bad", "posterior_toxic", "kept"])

    src = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id long, p_bad double, p_toxic double, posterior_bad double, posterior_toxic double, kept boolean")
