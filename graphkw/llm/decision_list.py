"""Quality rules as a learned decision list (operator 7).

Arrow batches give each whole text its statistics. The base rules are fixed. The
list behind them is learned by sequential covering: on a bounded sample of
labelled documents (the first ``sample`` by hash) that the base rules pass, a rule
grows by the threshold with the best information gain until it covers one class,
is pruned on rows set aside, and is taken if it is precise enough there; covered
rows leave and the next rule grows. The list becomes one ordered ``CASE`` over the
statistics, so the verdict itself runs inside the JVM.

Edge cases: a null or empty text has no words and fails the base; a null doc_id
stays null; repeated rows are judged each; without labels the list is empty and
the base alone decides; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import by_bytes, map_batches, table, text_of
from .quality_knn import labelled_sample

#: Fixed values of the base rules.
BLANKS, SYMBOLS, WINDOW = " \t\n\v\f\r", "#*$%&|<>", 8
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_upper", "n_digits", "n_marks", "n_lines", "n_distinct_words", "n_long_words")
#: Statistics that the list may use: name to (numerator, denominator).
RATIOS = {
    "symbol_share": ("n_symbols", "word_chars"),
    "upper_share": ("n_upper", "word_chars"),
    "digit_share": ("n_digits", "word_chars"),
    "mark_share": ("n_marks", "word_chars"),
    "symbols_per_word": ("n_symbols", "n_words"),
    "dup_line_share": ("n_dup_lines", "n_lines"),
    "repeat_share": ("n_repeat_words", "n_words"),
    "distinct_share": ("n_distinct_words", "n_words"),
    "long_share": ("n_long_words", "n_words"),
    "word_length": ("word_chars", "n_words"),
    "words_per_line": ("n_words", "n_lines"),
}


def _repeats(hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Words of each text (``bounds`` into ``hashes``) inside windows that its text holds twice or more."""
    n, words = len(bounds) - 1, len(hashes)
    if words < WINDOW:
        return np.zeros(n, np.int64)
    owner = np.repeat(np.arange(n), np.diff(bounds))
    key = np.zeros(words - WINDOW + 1, np.uint64)
    for k in range(WINDOW):
        key = key * np.uint64(0x9E3779B97F4A7C15) + hashes[k : k + len(key)]
        key ^= key >> np.uint64(29)
    first = owner[: len(key)]
    inside = first == owner[WINDOW - 1 :]
    key = (key ^ (first.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)))[inside]
    at = np.flatnonzero(inside)
    order = np.argsort(key)
    same = key[order][1:] == key[order][:-1]
    twice = np.zeros(len(key), bool)
    twice[order[1:]] |= same
    twice[order[:-1]] |= same
    edge = np.zeros(words + 1, np.int64)
    np.add.at(edge, at[twice], 1)
    np.add.at(edge, at[twice] + WINDOW, -1)
    return np.bincount(owner[np.cumsum(edge[:-1]) > 0], minlength=n)


def statistics(texts: list[str]) -> dict[str, np.ndarray]:
    """The columns of ``STATS`` for each text."""
    words = [t.encode("utf-8", "surrogatepass").split() for t in texts]
    n_words = np.fromiter(map(len, words), np.int64, len(texts))
    bounds = np.concatenate([[0], np.cumsum(n_words)])
    hashes = np.fromiter((h for w in words for h in map(hash, w)), np.int64, bounds[-1]).view(np.uint64)
    rows = []
    for t, w in zip(texts, words, strict=True):
        lines = [x for x in t.split("\n") if x.strip(BLANKS)]
        count = t.count
        rows.append((
            len(t) - sum(map(count, BLANKS)), sum(map(count, SYMBOLS)), len(lines) - len(set(lines)), sum(map(count, "ABCDEFGHIJKLMNOPQRSTUVWXYZÄÖÜÀÂÇÉÈÊÎÔÛÁÍÓÚÑ")),
            sum(map(count, "0123456789")), sum(map(count, "!?")), len(lines), len(set(w)), sum(len(x) > 20 for x in w),
        ))
    cols = np.array(rows, np.int64).reshape(len(texts), 9).T
    names = ("word_chars", "n_symbols", "n_dup_lines", "n_upper", "n_digits", "n_marks", "n_lines", "n_distinct_words", "n_long_words")
    return {"n_words": n_words, "n_repeat_words": _repeats(hashes, bounds), **dict(zip(names, cols, strict=True))}


def with_statistics(docs: DataFrame, extra: str = "") -> DataFrame:
    """doc_id, ``extra`` (a column of type double, if named) and the statistics of each text."""
    keep = ["doc_id", *([extra] if extra else [])]
    schema = "doc_id long, " + f"{extra} double, " * bool(extra) + ", ".join(f"{s} long" for s in STATS)

    def make():
        def work(batch):
            texts = batch.column(len(keep)).to_pylist()
            for a, b in by_bytes(texts, 1 << 21):
                got = statistics(texts[a:b])
                yield pa.RecordBatch.from_arrays([*(batch.column(k).slice(a, b - a) for k in range(len(keep))), *(pa.array(got[s], pa.int64()) for s in STATS)], [*keep, *STATS])

        return work

    columns = [docs["doc_id"].cast("long").alias("doc_id"), *([docs[extra].cast("double").alias(extra)] if extra else []), text_of().alias("text")]
    return map_batches(docs.select(columns), make, schema)


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


@dataclass(frozen=True)
class Threshold:
    stat: str
    above: bool
    bound: float

    def holds(self, table_: dict[str, np.ndarray]) -> np.ndarray:
        return table_[self.stat] > self.bound if self.above else table_[self.stat] <= self.bound

    def column(self) -> Column:
        top, bottom = (F.col(c) for c in RATIOS[self.stat])
        ratio = top / F.greatest(bottom, F.lit(1))
        return ratio > F.lit(float(self.bound)) if self.above else ratio <= F.lit(float(self.bound))


@dataclass(frozen=True)
class Rule:
    tests: tuple[Threshold, ...]
    keep: bool

    def holds(self, table_: dict[str, np.ndarray]) -> np.ndarray:
        return reduce(np.logical_and, (t.holds(table_) for t in self.tests))

    def column(self) -> Column:
        return reduce(lambda a, b: a & b, (t.column() for t in self.tests))


def _gain(p: np.ndarray, n: np.ndarray, p0: int, n0: int) -> np.ndarray:
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(p > 0, p * (np.log2(p / np.maximum(p + n, 1)) - np.log2(p0 / (p0 + n0))), -np.inf)


def _grow(x: dict[str, np.ndarray], y: np.ndarray, most: int) -> list[Threshold]:
    """Adds thresholds while they raise the share of the positive class."""
    tests: list[Threshold] = []
    inside = np.ones(len(y), bool)
    while len(tests) < most and (p0 := int(y[inside].sum())) and (n0 := int((~y[inside]).sum())):
        best: tuple[float, Threshold] | None = None
        for name, values in x.items():
            v, order = values[inside], np.argsort(values[inside], kind="stable")
            s, up = v[order], y[inside][order]
            cut = np.flatnonzero(s[1:] > s[:-1])
            if not len(cut):
                continue
            p, n = np.cumsum(up)[cut], np.cumsum(~up)[cut]
            for above, gain in ((False, _gain(p, n, p0, n0)), (True, _gain(p0 - p, n0 - n, p0, n0))):
                k = int(np.argmax(gain))
                if gain[k] > 1e-9 and (best is None or gain[k] > best[0]):
                    best = (float(gain[k]), Threshold(name, above, float((s[cut[k]] + s[cut[k] + 1]) / 2)))
        if not best:
            break
        tests.append(best[1])
        inside &= best[1].holds(x)
    return tests


def learn_rules(x: dict[str, np.ndarray], good: np.ndarray, fold: np.ndarray, precision: float = 0.95, least: int = 8, most_rules: int = 12, most_tests: int = 4) -> list[Rule]:
    """An ordered list of rules that drop documents. ``fold``: rows on which rules are pruned and judged."""
    rules: list[Rule] = []
    live = np.ones(len(good), bool)
    while len(rules) < most_rules:
        part = lambda m: ({k: v[m] for k, v in x.items()}, ~good[m])
        (gx, gy), (px, py) = part(live & ~fold), part(live & fold)
        tests = _grow(gx, gy, most_tests) if gy.any() else []
        def worth(ts, px=px, py=py):
            hit = Rule(tuple(ts), False).holds(px)
            p, n = int(py[hit].sum()), int((~py[hit]).sum())
            return (p - n) / max(1, p + n), p, n
        if not tests:
            break
        best = max(range(1, len(tests) + 1), key=lambda k: (worth(tests[:k])[0], -k))
        _, p, n = worth(tests[:best])
        if p + n < least or p < precision * (p + n):
            break
        rules.append(Rule(tuple(tests[:best]), False))
        live &= ~rules[-1].holds(x)
    return rules


def fit_rules(docs: DataFrame, labels: DataFrame, sample: int = 10_000) -> list[Rule]:
    """Learns from at most ``sample`` labelled documents; only their statistics reach the driver."""
    rows = with_statistics(labelled_sample(docs, labels, sample), "label").filter(~base_failed()).toPandas().sort_values(["doc_id", *STATS])
    x = {k: rows[a].to_numpy(float) / np.maximum(rows[b].to_numpy(float), 1) for k, (a, b) in RATIOS.items()}
    return learn_rules(x, rows["label"].to_numpy() > 0.5, np.arange(len(rows)) % 3 == 0)


def verdict(rules: Iterable[Rule]) -> Column:
    """The ordered conditional expression: false where the base or a rule drops the document."""
    out = F.when(base_failed(), F.lit(False))
    for rule in rules:
        out = out.when(rule.column(), F.lit(rule.keep))
    return out.otherwise(F.lit(True))


def judge(docs: DataFrame, rules: Iterable[Rule]) -> DataFrame:
    return with_statistics(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base_failed().alias("base_failed"), verdict(rules).alias("kept"))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return judge(docs, fit_rules(docs, table(spark, sf_dir, "labels")))
