"""Benchmark decontamination by training suffix arrays (operator 4).

Documents are taken in shards of bounded words. A shard's words become numbers of
the benchmark's vocabulary (0: not in it), and a suffix array is built over all
positions whose word is known: sorted by the first four words, ties by the next
four and so on, as deep as a window. Every suffix of every benchmark item is then
looked up by binary search: first over the packed four-word keys, then, within
that range, word by word. The range found holds every verbatim occurrence, with
its place; occurrences that cannot be extended to the left are extended to the
right for the longest match. Suffix arrays never leave their task, so nothing is
shuffled; the benchmark is broadcast after its size is checked.

A window is ``window`` consecutive words of an item; an item of fewer is one
window. A document word inside any occurrence is hit.

Edge cases: null or empty texts have no words and are never hit; items without
words are ignored; a null doc_id or item_id stays as it is (a null item counts as
the empty string); repeated documents are judged each; items of equal id count
once per document; an empty benchmark leaves all documents clean; further columns
are ignored by the query and kept by :func:`drop_contaminated`.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import by_bytes, map_batches, table, text_of

SCHEMA = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, longest_match long"
#: Bytes that end words: all ASCII but digits and (after lower-casing) a-z.
_TO_SPACE = bytes(c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 else 0x20 for c in bytes(range(256)).lower())


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_TO_SPACE).split() if text else []


class TestSet:
    """Benchmark items as numbers, with the windows that are searched."""

    __test__ = False

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int):
        items = [(i, w) for i, w in items if w]
        self.window, self.names = window, sorted({i for i, _ in items})
        self.number: dict[bytes, int] = {}
        name_at = {n: k for k, n in enumerate(self.names)}
        flat, starts, lengths, owners = [0], [], [], []
        for name, words in items:
            w = min(window, len(words))
            starts += range(len(flat), len(flat) + len(words) - w + 1)
            lengths += [w] * (len(words) - w + 1)
            owners += [name_at[name]] * (len(words) - w + 1)
            flat += [self.number.setdefault(x, len(self.number) + 1) for x in words] + [0]
        self.words = np.array(flat + [0] * (window + 4), np.int64)
        self.starts, self.lengths, self.owners = (np.array(x, np.int64) for x in (starts, lengths, owners))
        self.bits = 16 if len(self.number) < 1 << 16 else 31


class SuffixArray:
    """Known positions of a shard, sorted by their next ``depth`` words."""

    def __init__(self, words: np.ndarray, depth: int, bits: int):
        self.words, self.bits, self.per = np.concatenate([words, np.zeros(depth + 64, np.int64)]), bits, 64 // bits
        at = np.flatnonzero(words)
        keys = self._packed(self.words, at)
        order = np.argsort(keys)
        self.at, self.keys = at[order], keys[order]
        for skip in range(self.per, depth, self.per):
            self._settle_ties(skip)
        del self.ties

    def _packed(self, words: np.ndarray, at: np.ndarray, n: int | None = None, fill: int = 0) -> np.ndarray:
        key = np.zeros(len(at), np.uint64)
        for k in range(self.per):
            part = words[at + k].astype(np.uint64) if n is None or k < n else np.uint64(fill)
            key = key << np.uint64(self.bits) | part
        return key

    def _settle_ties(self, skip: int) -> None:
        """Sorts groups that agree in their first ``skip`` words by the words after; ``ties`` numbers the groups."""
        if skip == self.per:
            self.ties = np.cumsum(np.concatenate([[0], self.keys[1:] != self.keys[:-1]])) if len(self.keys) else np.zeros(0, np.int64)
        same = np.zeros(len(self.at), bool)
        if len(same):
            eq = self.ties[1:] == self.ties[:-1]
            same[1:] |= eq
            same[:-1] |= eq
        own = np.flatnonzero(same)
        if not len(own):
            return
        key = self._packed(self.words, self.at[own] + skip)
        order = np.lexsort((key, self.ties[own]))
        self.at[own] = self.at[own][order]
        group, key = self.ties[own], key[order]
        new = np.concatenate([[True], (group[1:] != group[:-1]) | (key[1:] != key[:-1])])
        fresh = np.zeros(len(self.at), np.int64)
        fresh[own[new]] = 1
        fresh[~same] = 1
        self.ties = np.cumsum(fresh)

    def find(self, test: np.ndarray, starts: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
        """Range of the suffixes that begin with each ``test[start : start + length]``."""
        n, top = min(length, self.per), (1 << self.bits) - 1
        low = np.searchsorted(self.keys, self._packed(test, starts, n, 0), "left")
        high = np.searchsorted(self.keys, self._packed(test, starts, n, top), "right")
        live = np.flatnonzero(low < high) if length > n else ()
        if len(live):
            low[live], high[live] = (self._bisect(test, starts[live], n, length, low[live], high[live], after) for after in (False, True))
        return low, high

    def _bisect(self, test, starts, skip, length, low, high, after: bool) -> np.ndarray:
        low, high = low.copy(), high.copy()
        ahead = np.arange(skip, length)
        want = test[starts[:, None] + ahead]
        while (open_ := np.flatnonzero(low < high)).size:
            mid = (low[open_] + high[open_]) // 2
            diff = self.words[self.at[mid][:, None] + ahead] - want[open_]
            first = diff[np.arange(len(diff)), np.argmax(diff != 0, axis=1)]
            right = first <= 0 if after else first < 0
            low[open_[right]] = mid[right] + 1
            high[open_[~right]] = mid[~right]
        return low


def occurrences(shard: np.ndarray, test: TestSet, most: int = 1 << 21) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(place in the shard, window number, words) of every occurrence of every window, in blocks."""
    array = SuffixArray(shard, test.window, test.bits)
    for length in np.unique(test.lengths):
        queries = np.flatnonzero(test.lengths == length)
        low, high = array.find(test.words, test.starts[queries], int(length))
        n = high - low
        queries, low, n = queries[n > 0], low[n > 0], n[n > 0]
        block = np.cumsum(n) // most
        for b in np.unique(block):
            q, a, m = queries[block == b], low[block == b], n[block == b]
            offsets = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
            yield array.at[np.repeat(a, m) + offsets], np.repeat(q, m), np.full(m.sum(), length)


def longest(shard: np.ndarray, test: TestSet, place: np.ndarray, window: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Matches that can't be extended to the left: which of ``place`` they are, their start in the test words, their length."""
    q = test.starts[window]
    before = np.where(place > 0, shard[np.maximum(place - 1, 0)], 0)
    head = np.flatnonzero((before != test.words[q - 1]) | (before == 0))
    p, q = place[head], q[head]
    n = np.zeros(len(head), np.int64)
    shard = np.append(shard, 0)
    live = np.arange(len(head))
    while live.size:
        a, b = shard[np.minimum(p[live] + n[live], len(shard) - 1)], test.words[np.minimum(q[live] + n[live], len(test.words) - 1)]
        live = live[(a == b) & (a > 0)]
        n[live] += 1
    return head, q, n


def judge_shard(texts: list[str | None], test: TestSet) -> dict[str, list]:
    """The columns of ``SCHEMA`` after doc_id for the documents of one shard."""
    words = [words_of(t) for t in texts]
    n_words = np.fromiter(map(len, words), np.int64, len(texts))
    get = test.number.get
    shard = np.fromiter((n for w in words for n in [*(get(x, 0) for x in w), 0]), np.int64, int(n_words.sum()) + len(texts))
    owner = np.repeat(np.arange(len(texts)), n_words + 1)
    edge = np.zeros(len(shard) + 1, np.int64)
    most, pairs = np.zeros(len(texts), np.int64), [np.empty(0, np.int64)]
    for place, window, length in occurrences(shard, test) if len(test.starts) else ():
        np.add.at(edge, place, 1)
        np.add.at(edge, place + length, -1)
        pairs.append(np.unique(owner[place] * len(test.names) + test.owners[window]))
        head, _, n = longest(shard, test, place, window)
        np.maximum.at(most, owner[place[head]], n)
    hit = np.bincount(owner[np.cumsum(edge[:-1]) > 0], minlength=len(texts))
    items: dict[int, list[str]] = {}
    for pair in np.unique(np.concatenate(pairs)).tolist():
        items.setdefault(pair // len(test.names), []).append(test.names[pair % len(test.names)])
    found = [sorted(items.get(k, ())) for k in range(len(texts))]
    return {
        "n_words": n_words.tolist(),
        "n_hit": hit.tolist(),
        "n_items": [len(x) for x in found],
        "items_sha256": [hashlib.sha256(",".join(x).encode()).hexdigest() for x in found],
        "contaminated": (hit > 0).tolist(),
        "longest_match": most.tolist(),
    }


def load_tests(benchmark: DataFrame, window: int = 10, max_bytes: int = 256 << 20) -> TestSet:
    """Reads the benchmark to the driver, after checking that its texts are at most ``max_bytes``."""
    size = benchmark.select(F.sum(F.octet_length("text"))).first()[0] or 0
    if size > max_bytes:
        raise ValueError(f"the benchmark has {size} bytes, more than {max_bytes}: decontaminate with its parts one after the other")
    rows = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item_id"), "text").collect()
    return TestSet(sorted((r["item_id"], words_of(r["text"])) for r in rows), window)


def find_contamination(docs: DataFrame, test: TestSet, shard_chars: int = 1 << 22) -> DataFrame:
    """One row per document with its hit words, the items behind them and its longest verbatim match."""
    shared = docs.sparkSession.sparkContext.broadcast(test)

    def make():
        def work(batch):
            texts = batch.column(1).to_pylist()
            for a, b in by_bytes(texts, shard_chars):
                got = judge_shard(texts[a:b], shared.value)
                yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0).slice(a, b - a), **got})

        return work

    return map_batches(docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of().alias("text")), make, SCHEMA)


def locate_matches(docs: DataFrame, test: TestSet, shard_chars: int = 1 << 22) -> DataFrame:
    """One row per match that can't be extended: the document, its first word there, the item and the length in words."""
    shared = docs.sparkSession.sparkContext.broadcast(test)

    def make():
        def work(batch):
            tests, texts, ids = shared.value, batch.column(1).to_pylist(), batch.column(0)
            for a, b in by_bytes(texts, shard_chars):
                numbers = [[tests.number.get(x, 0) for x in words_of(t)] + [0] for t in texts[a:b]]
                shard = np.array([n for w in numbers for n in w], np.int64)
                first = np.cumsum([0, *map(len, numbers)])
                owner = np.repeat(np.arange(b - a), np.diff(first))
                for place, window, _ in occurrences(shard, tests) if len(tests.starts) else ():
                    head, _, n = longest(shard, tests, place, window)
                    doc = owner[place[head]]
                    yield pa.RecordBatch.from_pydict({"doc_id": ids.slice(a, b - a).take(pa.array(doc)), "doc_word": place[head] - first[doc], "item_id": [tests.names[k] for k in tests.owners[window[head]]], "n_match": n})

        return work

    return map_batches(docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of().alias("text")), make, "doc_id long, doc_word long, item_id string, n_match long")


def drop_contaminated(docs: DataFrame, test: TestSet, shard_chars: int = 1 << 22) -> DataFrame:
    """The rows of ``docs`` without any hit word, all columns unchanged."""
    shared, at = docs.sparkSession.sparkContext.broadcast(test), docs.columns.index("text")

    def make():
        def work(batch):
            texts = batch.column(at).to_pylist()
            for a, b in by_bytes(texts, shard_chars):
                clean = [not x for x in judge_shard(texts[a:b], shared.value)["contaminated"]]
                yield batch.slice(a, b - a).filter(pa.array(clean, pa.bool_()))

        return work

    return map_batches(docs, make, docs.schema)


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_contamination(table(spark, sf_dir, "documents"), load_tests(table(spark, sf_dir, "benchmark")))


_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
OP4_SQL = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT item_id, w, least(10, len(w)) AS k FROM (SELECT CAST(item_id AS VARCHAR) AS item_id, {_WORDS} AS w FROM benchmark) WHERE len(w) > 0),
bw AS (SELECT DISTINCT item_id, k, array_to_string(w[i:i + k - 1], ' ') AS s, i FROM b, unnest(range(1, CAST(len(w) - k + 2 AS BIGINT))) AS t(i)),
dw AS (SELECT doc_id, i, k, array_to_string(w[i:i + k - 1], ' ') AS s
       FROM d, (SELECT DISTINCT k FROM bw), unnest(range(1, CAST(len(w) - k + 2 AS BIGINT))) AS t(i) WHERE len(w) >= k),
m AS (SELECT DISTINCT dw.doc_id, dw.i AS p, dw.k, bw.item_id, bw.i AS q FROM dw JOIN bw ON dw.s = bw.s AND dw.k = bw.k),
runs AS (SELECT doc_id, item_id, p - q AS diagonal, p, k, p - row_number() OVER (PARTITION BY doc_id, item_id, k, p - q ORDER BY p) AS run FROM m),
far AS (SELECT doc_id, max(n) AS longest_match FROM (SELECT doc_id, max(k) + count(*) - 1 AS n FROM runs GROUP BY doc_id, item_id, k, diagonal, run) GROUP BY doc_id),
hits AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM m, unnest(range(p, p + k)) AS t(j) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated, CAST(coalesce(longest_match, 0) AS BIGINT) AS longest_match
FROM d LEFT JOIN hits USING (doc_id) LEFT JOIN items USING (doc_id) LEFT JOIN far USING (doc_id)
"""
