"""Quality rules: text statistics, and decision lists learned from labelled statistics.

``statistics`` counts, for every whole text, the quantities that the rules use. ``learn`` grows an ordered list of
rules by sequential covering: each rule is a conjunction of thresholds on statistics, grown on one part of the labelled rows
by information gain, pruned from its end on the other part, and kept while it rejects
precisely enough there; the rows that it covers are then set aside. ``RuleList.verdict`` turns the
list into one nested Spark conditional expression, so it runs inside generated code and can be read.

The learner sees at most ``max_labelled`` labelled rows (those with the least hash of doc_id); everything else
covers all rows. Null or empty text: all counts 0. Null doc_id: kept as null, never labelled. Labels with
null quality are ignored; a document with several labels counts once for each. Without labelled rows of both classes the list is
empty and its verdict is true. Repeated rows give repeated results; other columns of the input are not used.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textkit as tk

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_letters", "n_bangs", "n_distinct_words")
SCHEMA = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS)

#: The statistics that rules test: name -> (numerator, denominator or None)
RATIOS = {
    "words": ("n_words", None),
    "mean_word_chars": ("word_chars", "n_words"),
    "symbols_per_word": ("n_symbols", "n_words"),
    "duplicate_line_share": ("n_dup_lines", "n_lines"),
    "repeated_word_share": ("n_repeat_words", "n_words"),
    "upper_share": ("n_upper", "n_letters"),
    "bangs_per_word": ("n_bangs", "n_words"),
    "distinct_word_share": ("n_distinct_words", "n_words"),
}

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_LETTER = _UPPER.copy()
_LETTER[97:123] = True
_BANG = np.zeros(256, bool)
_BANG[list(b"!?")] = True
WINDOW = 8


def slab_counts(s: tk.Slab) -> dict[str, np.ndarray]:
    start, end = s.words()
    cuts = s.per_doc(start)
    n_words = np.diff(cuts)
    h = s.hash(start, end)
    lead = tk.LEAD_BYTE & tk.WORD_BYTE
    out = {
        "n_words": n_words,
        "word_chars": s.sums_by_doc(lead[s.data]),
        "n_symbols": s.sums_by_doc(_SYMBOL[s.data]),
        "n_upper": s.sums_by_doc(_UPPER[s.data]),
        "n_letters": s.sums_by_doc(_LETTER[s.data]),
        "n_bangs": s.sums_by_doc(_BANG[s.data]),
    }
    salt = tk.mix(np.arange(1, s.n + 1).astype(np.uint64))
    # lines that hold a word
    newline = np.flatnonzero(s.data == 10)
    line_start = np.sort(np.concatenate([s.off[:-1], newline + 1]))
    line_doc = np.searchsorted(s.off, line_start, side="right") - 1
    line_end = np.append(line_start[1:], len(s.data))
    line_end = line_end - np.isin(line_end - 1, newline, assume_unique=False)
    inside = (line_start < line_end) & (line_doc < s.n)
    line_start, line_end, line_doc = line_start[inside], line_end[inside], line_doc[inside]
    busy = np.searchsorted(start, line_end) > np.searchsorted(start, line_start)
    line_start, line_end, line_doc = line_start[busy], line_end[busy], line_doc[busy]
    n_lines = np.bincount(line_doc, minlength=s.n)
    _, at = np.unique(s.hash(line_start, line_end) ^ salt[line_doc], return_index=True)
    out["n_lines"] = n_lines
    out["n_dup_lines"] = n_lines - np.bincount(line_doc[at], minlength=s.n)
    # words inside windows that occur twice or more
    first, doc = tk.windows(cuts, WINDOW)
    key = tk.rolling(h, WINDOW)[first] ^ salt[doc] if len(first) else np.empty(0, np.uint64)
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    twice = np.zeros(len(key), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    cover = np.zeros(len(start) + 1, np.int64)
    np.add.at(cover, first[twice], 1)
    np.add.at(cover, first[twice] + WINDOW, -1)
    covered = np.concatenate([[0], np.cumsum(np.cumsum(cover)[:-1] > 0)])
    out["n_repeat_words"] = covered[cuts[1:]] - covered[cuts[:-1]]
    word_doc = np.repeat(np.arange(s.n), n_words)
    _, at = np.unique(h ^ salt[word_doc], return_index=True)
    out["n_distinct_words"] = np.bincount(word_doc[at], minlength=s.n)
    return out


@tk.tidy
def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for i, j, s in tk.slabs(b.column(1)):
            c = slab_counts(s)
            yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), *(pa.array(np.asarray(c[k], np.int64)) for k in COUNTS)], names=["doc_id", *COUNTS])


def statistics(docs: DataFrame, text: str = "text") -> DataFrame:
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs[text].cast("string").alias("text")).mapInArrow(_count, SCHEMA)


def base_failed(prefix: str = "") -> Column:
    n = F.col(f"{prefix}n_words")
    return (n < 20) | (100 * F.col(f"{prefix}n_repeat_words") > 30 * n)


@dataclass(frozen=True)
class Condition:
    statistic: str
    above: bool
    threshold: float

    def column(self, prefix: str = "") -> Column:
        top, bottom = RATIOS[self.statistic]
        value = F.col(prefix + top).cast("double") if bottom is None else F.col(prefix + top) / F.greatest(F.col(prefix + bottom), F.lit(1))
        return value >= self.threshold if self.above else value <= self.threshold

    def test(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return x[self.statistic] >= self.threshold if self.above else x[self.statistic] <= self.threshold

    def __str__(self) -> str:
        return f"{self.statistic} {'>=' if self.above else '<='} {self.threshold:.6g}"


@dataclass
class RuleList:
    """Ordered rules that reject; what none covers is kept."""

    rules: list[tuple[Condition, ...]] = field(default_factory=list)

    def verdict(self, prefix: str = "") -> Column:
        """True: keep."""
        out = F.lit(True)
        for rule in reversed(self.rules):
            test = rule[0].column(prefix)
            for c in rule[1:]:
                test = test & c.column(prefix)
            out = F.when(test, F.lit(False)).otherwise(out)
        return out

    def __str__(self) -> str:
        return "\n".join([*("reject if " + " and ".join(map(str, r)) for r in self.rules), "keep"])


def _ratio_arrays(c: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    return {k: c[a].astype(float) if b is None else c[a] / np.maximum(c[b], 1) for k, (a, b) in RATIOS.items()}


def learn_rules(x: dict[str, np.ndarray], bad: np.ndarray, part: np.ndarray, min_precision: float, max_rules: int, max_conditions: int, min_cover: int) -> RuleList:
    """x: statistics of labelled rows; bad: rows to reject; part: True for rows that grow, False for rows that prune."""
    left = np.ones(len(bad), bool)
    rules: list[tuple[Condition, ...]] = []
    cuts = {k: np.unique(np.quantile(v, np.linspace(0, 1, 65))) for k, v in x.items()} if len(bad) else {}
    while len(rules) < max_rules:
        live = left & part
        rule: list[Condition] = []
        covered = live.copy()
        while len(rule) < max_conditions and (covered & ~bad).any() and (covered & bad).any():
            p0, n0 = (covered & bad).sum(), (covered & ~bad).sum()
            base, best, gain = np.log2(p0 / (p0 + n0)), None, 1e-9
            for k, at in cuts.items():
                for above in (True, False):
                    for t in at:
                        c = Condition(k, above, float(t))
                        m = covered & c.test(x)
                        p = (m & bad).sum()
                        if p >= min_cover and (g := p * (np.log2(p / m.sum()) - base)) > gain:
                            best, gain = c, g
            if best is None:
                break
            rule.append(best)
            covered &= best.test(x)
        if not rule:
            break

        def worth(r: list[Condition]) -> tuple[float, int]:
            m = left & ~part
            for c in r:
                m = m & c.test(x)
            p, n = (m & bad).sum(), (m & ~bad).sum()
            return ((p - n) / max(p + n, 1), p)

        rule = max((rule[:i] for i in range(len(rule), 0, -1)), key=worth)
        m = left.copy()
        for c in rule:
            m &= c.test(x)
        checked = m & ~part
        if checked.sum() < min_cover or bad[checked].mean() < min_precision:
            break
        rules.append(tuple(rule))
        left &= ~m
    return RuleList(rules)


PREFIX = "__rule_"


def filter_documents(docs: DataFrame, labels: DataFrame, max_labelled: int = 20_000) -> DataFrame:
    """The rows of docs, with all their columns, that the base test and the learned rules keep."""
    some = labels.where("quality is not null").select(labels["doc_id"].cast("long").alias("doc_id")).where("doc_id is not null").distinct()
    some = some.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)  # bounded, so it can be sent
    rules = learn(statistics(docs.join(F.broadcast(some), docs["doc_id"].cast("long") == some["doc_id"], "left_semi")), labels, max_labelled)
    names, at = docs.columns, docs.columns.index("text")

    @tk.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, s in tk.slabs(b.column(at).cast(pa.string())):
                c = slab_counts(s)
                yield pa.RecordBatch.from_arrays([*(x.slice(i, j - i) for x in b.columns), *(pa.array(np.asarray(c[k], np.int64)) for k in COUNTS)], names=[*names, *(PREFIX + k for k in COUNTS)])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + ", " + ", ".join(f"{PREFIX}{c} long" for c in COUNTS)
    counted = docs.mapInArrow(run, schema)
    return counted.where(~base_failed(PREFIX) & rules.verdict(PREFIX)).select(*names)


def learn(stats: DataFrame, labels: DataFrame, max_labelled: int = 20_000, min_precision: float = 0.9, max_rules: int = 8, max_conditions: int = 3, min_cover: int = 3) -> RuleList:
    marked = labels.select(labels["doc_id"].cast("long").alias("doc_id"), (labels["quality"].cast("int") == 0).alias("__bad")).where("doc_id is not null and __bad is not null")
    marked = marked.orderBy(F.xxhash64("doc_id"), "doc_id", "__bad").limit(max_labelled)
    rows = stats.join(marked, "doc_id").select("doc_id", "__bad", *COUNTS).limit(4 * max_labelled).toPandas()  # ids may be repeated
    rows = rows.sort_values(["doc_id", "__bad"]).reset_index(drop=True)
    if rows["__bad"].nunique() < 2:
        return RuleList()
    x = _ratio_arrays({c: rows[c].to_numpy() for c in COUNTS})
    part = tk.mix(rows["doc_id"].to_numpy().astype(np.uint64)) % np.uint64(3) != 0
    return learn_rules(x, rows["__bad"].to_numpy(bool), part, min_precision, max_rules, max_conditions, min_cover)
