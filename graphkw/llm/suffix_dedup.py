"""Removal of repeated byte strings by blockwise suffix sorting (operator 5).

A byte goes if a string of ``length`` bytes over it also starts anywhere else.
Sorting all suffixes of a corpus at once can't be done in bounded memory, so
suffixes are put into buckets that no equal strings can straddle, and buckets are
sorted one at a time:

1. Every window of ``length`` bytes names its anchor, the ``gram`` bytes in it with
   the least fingerprint. Equal windows have equal anchors at equal distances.
   Windows in a row with one anchor make one context. Each text is read once and
   yields a short row per context.
2. Contexts whose anchor is unique hold no repeated window. Contexts that occur
   twice as a whole hold only repeated windows. Both are settled by counting.
3. The others - the ends of repeats and what surrounds edits - are suffix-sorted,
   an anchor's windows split in two by the bytes left or right of the anchor. A
   task reads its buckets in order and fills blocks of bounded size. Within a
   block, the suffixes at difference-cover positions are ranked beforehand by
   doubling; suffixes are sorted by bucket and their first ``v`` bytes, and ties
   (buckets share long strings, so most tie) are resolved by the ranks of the
   first positions that are in the cover for both. Neighbours in the order that
   agree in ``length`` bytes, compared byte by byte, are repeats.
4. Buckets above ``bucket_rows`` contexts would not fit a block; their windows are
   counted by 128-bit fingerprints instead, which no group size can hurt.

Edge cases: null and short texts keep all bytes; matches never cross documents;
repeated rows repeat each other; a null doc_id stays null; texts beyond 8 MB are
read in overlapping stretches; further columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cmp_to_key, lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .anchors import Fingerprints, window_argmin
from .base import Stage, by_bytes, map_batches, table, text_of
from .sketches import mix

#: Bytes of a stretch of text that is looked at once.
STRETCH = 1 << 21


def cover(m: int) -> tuple[np.ndarray, np.ndarray]:
    """A difference cover modulo v = m * m as flags, and for any two residues the least step that brings both into it."""
    v = m * m
    inside = np.zeros(v, bool)
    inside[:m] = inside[::m] = True
    r = np.arange(v)
    steps = np.full((v, v), v, np.int64)
    for d in range(v - 1, -1, -1):
        ok = inside[(r + d) % v]
        steps[np.ix_(ok, ok)] = d
    return inside, steps


@lru_cache(maxsize=2)
def _cover(m: int):
    return cover(m)


def _words(data: np.ndarray, at: np.ndarray, n: int) -> list[np.ndarray]:
    """``n`` big-endian 64-bit words from each place, last first, as lexsort wants them."""
    view = np.lib.stride_tricks.sliding_window_view(data, 8)
    return [np.ascontiguousarray(view[at + 8 * k]).view(">u8").ravel().astype(np.uint64) for k in range(n - 1, -1, -1)]


def _numbered(order: np.ndarray, keys: list[np.ndarray]) -> np.ndarray:
    """Rank of each row under ``keys`` (equal rows share one), given their sorted order."""
    new = np.zeros(len(order), bool)
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    out = np.empty(len(order), np.int64)
    out[order] = np.cumsum(new)
    return out


class CoverRanks:
    """Ranks of the suffixes at cover positions by at least their first ``depth`` bytes."""

    def __init__(self, data: np.ndarray, depth: int, m: int = 8):
        self.v = v = m * m
        self.inside, self.steps = _cover(m)
        padded = np.concatenate([data, np.zeros(v + 8, np.uint8)])
        at = np.flatnonzero(np.resize(self.inside, len(data)))
        self.rank = np.zeros(len(data) + 2 * v, np.int64)
        if not len(at):
            return
        keys = _words(padded, at, v // 8)
        ranks, done = _numbered(np.lexsort(keys), keys) + 1, v
        while done < depth:
            self.rank[at] = ranks
            ahead = np.where(at + done < len(data), self.rank[np.minimum(at + done, len(data))], 0)
            key = (ranks << np.int64(32)) | ahead
            ranks, done = _numbered(np.argsort(key, kind="stable"), [key]) + 1, 2 * done
        self.rank[at] = ranks


def sort_suffixes(data: np.ndarray, starts: np.ndarray, bucket: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Order of the suffixes by bucket and by at least their first ``depth`` bytes; and which share v bytes with the one before."""
    ranks = CoverRanks(data, depth)
    v = ranks.v
    keys = [*_words(np.concatenate([data, np.zeros(v + 8, np.uint8)]), starts, v // 8), bucket]
    order = np.lexsort(keys)
    group = _numbered(order, keys)
    residue = starts % v
    # Ties of one residue have one next cover position each and sort by its rank; mixed ties go pair by pair.
    step = ranks.steps[residue, residue]
    order = np.lexsort((ranks.rank[starts + step], group))
    g, r = group[order], residue[order]
    tied = np.concatenate([[False], g[1:] == g[:-1]]) if len(g) else np.zeros(0, bool)
    odd = np.flatnonzero(tied & np.concatenate([[False], r[1:] != r[:-1]])) if len(g) else ()

    def compare(i: int, j: int) -> int:
        a, b = int(starts[i]), int(starts[j])
        d = int(ranks.steps[a % v, b % v])
        return int(ranks.rank[a + d] - ranks.rank[b + d])

    for k in np.unique(g[odd]) if len(odd) else ():
        a, b = np.searchsorted(g, [k, k + 1])
        order[a:b] = sorted(order[a:b].tolist(), key=cmp_to_key(compare))
    return order, tied


def repeated_windows(data: np.ndarray, starts: np.ndarray, bucket: np.ndarray, length: int, chunk: int = 8192) -> np.ndarray:
    """Which windows equal another of their bucket in ``length`` bytes."""
    order, tied = sort_suffixes(data, starts, bucket, length)
    out = np.zeros(len(starts), bool)
    b = bucket[order]
    pairs = np.flatnonzero(tied if length >= 64 else np.concatenate([[False], b[1:] == b[:-1]]))
    view = np.lib.stride_tricks.sliding_window_view(data, length)
    for k in range(0, len(pairs), chunk):
        p = pairs[k : k + chunk]
        same = p[(view[starts[order[p]]] == view[starts[order[p - 1]]]).all(axis=1)]
        out[order[same]] = out[order[same - 1]] = True
    return out


def _stretches(raw: bytes, length: int, most: int = 1 << 23) -> Iterator[tuple[int, bytes]]:
    """A text in parts of at most ``most`` windows each, which overlap by a window less a byte."""
    for at in range(0, max(1, len(raw) - length + 1), most):
        yield at, raw[at : at + most + length - 1]


def contexts(texts: list[bytes], length: int, gram: int) -> tuple[np.ndarray, ...]:
    """Of all contexts: number of the text, gram and context fingerprints, anchor, first and last window in the text."""
    found = []
    parts = [(k, at, part) for k, raw in enumerate(texts) if len(raw) >= length for at, part in _stretches(raw, length)]
    for a, b in by_bytes([p[2] for p in parts], STRETCH):
        data = b"".join(p[2] for p in parts[a:b])
        sizes = np.array([len(p[2]) for p in parts[a:b]])
        ends = np.cumsum(sizes)
        prints = Fingerprints(data)
        grams = prints.all(gram)
        anchor = window_argmin(grams, length - gram + 1)
        owner = np.repeat(np.arange(b - a), sizes)[: len(anchor)]
        start = np.flatnonzero(np.arange(len(anchor)) + length <= ends[owner])
        anchor, owner = anchor[start], owner[start]
        first = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (owner[1:] != owner[:-1])]))
        lo, hi, anchor, owner = start[first], start[np.append(first[1:], len(start)) - 1], anchor[first], owner[first]
        whole = mix(prints.of(lo, hi + length) + (anchor - lo).astype(np.uint64))
        shift = np.array([p[1] for p in parts[a:b]]) - (ends - sizes)
        text = np.array([p[0] for p in parts[a:b]])
        found.append((text[owner], grams[anchor].view(np.int64), whole.view(np.int64), anchor + shift[owner], lo + shift[owner], hi + shift[owner]))
    if not found:
        return tuple(np.empty(0, np.int64) for _ in range(6))
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.xxhash64(text_of()).alias("tk"), text_of().alias("text"))


def _utf8(texts: list[str | None]) -> list[bytes]:
    return [(t or "").encode("utf-8", "surrogatepass") for t in texts]


def context_rows(docs: DataFrame, length: int, gram: int) -> DataFrame:
    def make():
        def work(batch):
            ids, keys = batch.column(0), batch.column(1)
            texts = batch.column(2).to_pylist()
            for a, b in by_bytes(texts, 4 * STRETCH):
                text, *rest = contexts(_utf8(texts[a:b]), length, gram)
                at = pa.array(text + a)
                yield pa.RecordBatch.from_arrays([ids.take(at), keys.take(at), *(pa.array(x) for x in rest[:2]), *(pa.array(x.astype(np.int32)) for x in rest[2:])], ["doc_id", "tk", "g", "c", "a", "lo", "hi"])

        return work

    return map_batches(_keyed(docs), make, "doc_id long, tk long, g long, c long, a int, lo int, hi int")


def _halves(raw: bytes, g: int, a: int, lo: int, hi: int, length: int, gram: int) -> Iterator[tuple[int, int, int]]:
    """(bucket, first window, last window) of the windows that reach far to the left of the anchor, and of the others."""
    half = (length - gram + 1) // 2
    cut = a - half
    mark = np.uint64(g & 0xFFFFFFFFFFFFFFFF)
    for side, first, last, x, y in ((1, lo, min(hi, cut), cut, a), (2, max(lo, cut + 1), hi, a + gram, cut + 1 + length)):
        if first <= last:
            shared = int.from_bytes(hashlib.blake2b(raw[x:y], digest_size=8).digest(), "little")
            yield int(mix(np.array([mark ^ np.uint64(shared)]) + np.uint64(side)).view(np.int64)[0]), first, last


def _bucket_rows(docs: DataFrame, wanted: DataFrame, length: int, gram: int) -> DataFrame:
    """The bytes of the contexts that are to be sorted, with their buckets."""
    by_doc = wanted.groupBy(F.col("doc_id").alias("own_doc"), F.col("tk").alias("own_tk")).agg(F.collect_set(F.struct("g", "a", "lo", "hi", "own")).alias("parts"))
    rows = _keyed(docs).join(by_doc, (F.col("tk") == F.col("own_tk")) & F.col("doc_id").eqNullSafe(F.col("own_doc"))).select("doc_id", "tk", "text", "parts")

    def make():
        def work(batch):
            for doc, tk, text, parts in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                raw = text.encode("utf-8", "surrogatepass")
                out = []
                for p in parts:
                    for key, first, last in _halves(raw, p["g"], p["a"], p["lo"], p["hi"], length, gram):
                        out.append((key, doc, tk, p["own"], first, last, p["a"], raw[first : last + length]))
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], ["key", "doc_id", "tk", "own", "lo", "hi", "a", "bytes"])

        return work

    return map_batches(rows, make, "key long, doc_id long, tk long, own boolean, lo int, hi int, a int, bytes binary")


def _runs(flags: np.ndarray) -> Iterator[tuple[int, int]]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]])))
    yield from zip(edge[::2].tolist(), (edge[1::2] - 1).tolist(), strict=True)


def sort_block(rows: list[tuple], length: int, v: int = 64) -> list[tuple]:
    """Runs of repeated windows (doc_id, tk, first, last) of the block's own contexts. Anchors are placed at one residue, so that equal windows tie on it."""
    at, pieces, begin = 0, [], []
    for *_, lo, _, a, raw in rows:
        pad = (lo - a - at) % v
        pieces += [bytes(pad), raw]
        begin.append(at + pad)
        at += pad + len(raw)
    data = np.frombuffer(b"".join(pieces), np.uint8)
    count = np.array([r[5] - r[4] + 1 for r in rows])
    first = np.cumsum(count) - count
    starts = np.arange(count.sum()) - np.repeat(first - np.array(begin), count)
    flags = repeated_windows(data, starts, np.repeat(np.array([r[0] for r in rows]), count), length)
    return [(r[1], r[2], r[4] + x, r[4] + y) for r, f, n in zip(rows, first.tolist(), count.tolist(), strict=True) if r[3] for x, y in _runs(flags[f : f + n])]


def _sort_buckets(length: int, block_bytes: int):
    """Reads rows sorted by bucket; sorts blocks of whole buckets."""

    def run(batches):
        def done(rows):
            found = sort_block(rows, length)
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32())
            return pa.RecordBatch.from_arrays([pa.array([f[k] for f in found], t) for k, t in enumerate(kinds)], ["doc_id", "tk", "lo", "hi"])

        rows, held = [], 0
        for batch in batches:
            for row in zip(*(batch.column(k).to_pylist() for k in range(8)), strict=True):
                if held >= block_bytes and row[0] != rows[-1][0]:
                    yield done(rows)
                    rows, held = [], 0
                rows.append(row)
                held += len(row[7])
        if rows:
            yield done(rows)

    return run


def _print_windows(length: int):
    """Two fingerprints of every window of the contexts."""

    def work(batch):
        for key, doc, tk, own, lo, hi, _, raw in zip(*(batch.column(k).to_pylist() for k in range(8)), strict=True):
            n = hi - lo + 1
            one = Fingerprints(raw).all(length)[:n]
            two = Fingerprints(raw[::-1]).all(length)[::-1][:n]
            yield pa.RecordBatch.from_pydict({"key": [key] * n, "f1": one.view(np.int64), "f2": np.ascontiguousarray(two).view(np.int64), "doc_id": pa.array([doc] * n, pa.int64()), "tk": [tk] * n, "own": [own] * n, "lo": pa.array(range(lo, hi + 1), pa.int32())})

    return work


def repeated_runs(docs: DataFrame, length: int = 400, gram: int = 256, block_bytes: int = 1 << 22, bucket_rows: int = 20_000) -> DataFrame:
    """(doc_id, tk, lo, hi): runs of windows, by their first bytes, that also start elsewhere."""
    seen = Stage(context_rows(docs, length, gram), "contexts")
    grams = seen.df.groupBy("g").agg(F.count("*").alias("n"), F.min("c").alias("least"), F.max("c").alias("most")).filter("n > 1")
    grams = Stage(grams, "grams").df  # read back, both sides of the join are dealt out anew and a very common anchor can be split
    many = Stage(seen.df.join(grams, "g").select("g", "c", "doc_id", "tk", "a", "lo", "hi", (F.col("least") == F.col("most")).alias("settled")), "repeats")
    seen.drop()
    mixed = many.df.filter("NOT settled")
    classes = Stage(mixed.groupBy("g", "c").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "tk", "a", "lo", "hi")).alias("one")), "classes").df
    twice = mixed.join(classes.filter("n > 1").select("g", "c"), ["g", "c"]).select("doc_id", "tk", "lo", "hi")
    runs = many.df.filter("settled").select("doc_id", "tk", "lo", "hi").unionByName(twice)

    ends = classes.groupBy("g").agg(F.min("n").alias("least")).filter("least = 1").select("g")
    wanted = classes.join(ends, "g").select("g", "one.*", (F.col("n") == 1).alias("own"))
    rows = Stage(_bucket_rows(docs, wanted, length, gram), "buckets").df
    sizes = rows.groupBy("key").agg(F.count("*").alias("n"), F.max("own").alias("any_own")).filter("n > 1 AND any_own")
    small = rows.join(sizes.filter(F.col("n") <= bucket_rows).select("key"), "key")
    sorted_ = small.repartition("key").sortWithinPartitions("key").mapInArrow(_sort_buckets(length, block_bytes), "doc_id long, tk long, lo int, hi int")
    large = rows.join(sizes.filter(F.col("n") > bucket_rows).select("key"), "key")
    windows = map_batches(large, lambda: _print_windows(length), "key long, f1 long, f2 long, doc_id long, tk long, own boolean, lo int")
    common = windows.groupBy("key", "f1", "f2").agg(F.count("*").alias("n")).filter("n > 1").select("key", "f1", "f2")
    counted = windows.filter("own").join(common, ["key", "f1", "f2"]).select("doc_id", "tk", "lo", F.col("lo").alias("hi"))
    return runs.unionByName(sorted_).unionByName(counted)


def strip(raw: bytes, runs: list[tuple[int, int]], length: int) -> tuple[bytes, int, int]:
    """What is left without the windows of ``runs``; bytes and spans removed."""
    gone = np.zeros(len(raw) + 1, np.int64)
    for lo, hi in runs:
        gone[lo] += 1
        gone[hi + length] -= 1
    out = np.cumsum(gone)[:-1] > 0
    spans = int(np.count_nonzero(np.diff(np.concatenate([[0], out.astype(np.int8)])) == 1))
    return np.frombuffer(raw, np.uint8)[~out].tobytes(), int(out.sum()), spans


def remove_repeats(docs: DataFrame, length: int = 400, gram: int = 256, with_bytes: bool = False) -> DataFrame:
    """One row per document: bytes, bytes and spans removed, and the hash (or also the bytes) of what is left."""
    runs = repeated_runs(docs, length, gram)
    by_doc = runs.groupBy(F.col("doc_id").alias("own_doc"), F.col("tk").alias("own_tk")).agg(F.collect_set(F.struct("lo", "hi")).alias("runs"))
    rows = _keyed(docs).join(by_doc, (F.col("tk") == F.col("own_tk")) & F.col("doc_id").eqNullSafe(F.col("own_doc")), "left").select("doc_id", "text", "runs")

    def make():
        def work(batch):
            out = []
            for doc, text, runs in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                raw = text.encode("utf-8", "surrogatepass")
                left, n, spans = strip(raw, [(r["lo"], r["hi"]) for r in runs], length) if runs else (raw, 0, 0)
                out.append((doc, len(raw), n, spans, hashlib.sha256(left).hexdigest(), *([left] if with_bytes else [])))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), *([pa.binary()] if with_bytes else []))
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names[: len(kinds)])

        return work

    return map_batches(rows, make, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * with_bytes)


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"))


OP5_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
w AS (SELECT r, i, md5(substr(x, 2 * i + 1, 800)) AS h FROM d, unnest(range(CAST(length(x) // 2 - 399 AS BIGINT))) AS t(i) WHERE length(x) >= 800),
s AS (SELECT r, i, i - lag(i) OVER (PARTITION BY r ORDER BY i) AS gap FROM w WHERE h IN (SELECT h FROM w GROUP BY h HAVING count(*) > 1)),
g AS (SELECT r, i, sum(CASE WHEN gap <= 400 THEN 0 ELSE 1 END) OVER (PARTITION BY r ORDER BY i) AS g FROM s),
runs AS (SELECT r, min(i) AS a, max(i) + 400 AS b FROM g GROUP BY r, g),
p AS (SELECT r, a, b, coalesce(lag(b) OVER (PARTITION BY r ORDER BY a), 0) AS before FROM runs),
k AS (SELECT p.r, CAST(sum(b - a) AS BIGINT) AS n, count(*) AS c, string_agg(substr(x, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) AS head, max(b) AS tail FROM p JOIN d ON d.r = p.r GROUP BY p.r)
SELECT doc_id, CAST(length(x) // 2 AS BIGINT) AS n_bytes, coalesce(n, 0) AS n_removed, coalesce(c, 0) AS n_spans, sha256(unhex(coalesce(head, '') || substr(x, 2 * coalesce(tail, 0) + 1))) AS kept_sha256
FROM d LEFT JOIN k ON k.r = d.r
"""
