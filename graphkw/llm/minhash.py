"""Near-duplicates by fast similarity sketches (operator 3).

Each text's shingle set gets a sketch of hashed bins that all fill (see
:mod:`sketches`); neighbouring coordinates form bands. Documents of equal sets are
one class. Classes that share a band are candidates: the connected groups of the
band graph (a star for each band, never all its pairs) are families. Within a
family, every pair is verified exactly on full sets: families are cut into blocks
and each pair of blocks is one cell, whose intersection sizes come from matrix
products over the shingles that at least two of its members share. A cell returns
a spanning forest of its links. So no task holds more than two blocks of sets, no
pair of rows is ever emitted, and no link is lost but by the sketch (with 32 bands
of 4 and similarity 0.85, one in 10**10).

Families are small against the corpus; only their members' texts are read again.

Edge cases: null or empty texts and texts without words have an empty set, link
to nothing and stay; a null doc_id is kept apart (it sorts after all others for
the smallest id); repeated rows are one class; further columns are ignored by the
query and kept by :func:`drop_near_duplicates`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import Stage, by_bytes, map_batches, table, text_of
from .components import components
from .sketches import WordHashes, bands, fast_sketch, mix, shingle_set

BINS, BANDS = 128, 32


def _keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text and a key of the text."""
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.xxhash64(text_of()).alias("tk"), text_of().alias("text"))


def sketched(docs: DataFrame, size: int) -> DataFrame:
    """doc_id, tk, the set's size and key, and its bands (null for an empty set)."""

    def make():
        hashes = WordHashes()

        def work(batch):
            for a, b in by_bytes(batch.column(2).to_pylist(), 1 << 20):
                sets = [shingle_set(t, size, hashes) for t in batch.column(2).slice(a, b - a).to_pylist()]
                keys = [(int(x.sum(dtype=np.uint64).view(np.int64)), int(mix(x).sum(dtype=np.uint64).view(np.int64))) if len(x) else (None, None) for x in sets]
                columns = [batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.array(map(len, sets), pa.int64()), *(pa.array([k[i] for k in keys], pa.int64()) for i in (0, 1))]
                columns.append(pa.array([bands(fast_sketch(x, BINS), BANDS).view(np.int64) if len(x) else None for x in sets], pa.list_(pa.int64())))
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "tk", "n", "s1", "s2", "bands"])

        return work

    return map_batches(_keyed(docs), make, "doc_id long, tk long, n long, s1 long, s2 long, bands array<long>")


def _sets_of(docs: DataFrame, members: DataFrame, size: int) -> DataFrame:
    """The full sets of the representatives in ``members`` (id, tk, doc_id)."""

    def make():
        hashes = WordHashes()

        def work(batch):
            for a, b in by_bytes(batch.column(1).to_pylist(), 1 << 20):
                sets = [shingle_set(t, size, hashes).tobytes() for t in batch.column(1).slice(a, b - a).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(sets, pa.binary())], ["id", "items"])

        return work

    named = members.select("id", F.col("tk").alias("own_tk"), F.col("doc_id").alias("own_doc"))
    texts = _keyed(docs).join(named, (F.col("tk") == F.col("own_tk")) & F.col("doc_id").eqNullSafe(F.col("own_doc")))
    return map_batches(texts.select("id", "text"), make, "id long, items binary").dropDuplicates(["id"])


def linked(sets: list[np.ndarray], left: np.ndarray, num: int, den: int, columns: int = 4096) -> list[tuple[int, int]]:
    """A spanning forest of the links of one cell. ``left``: members of the first block; with two blocks only cross pairs are tested."""
    sizes = np.array([len(s) for s in sets], np.int64)
    flat = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), sizes)
    _, token, count = np.unique(flat, return_inverse=True, return_counts=True)
    shared = count[token] > 1
    owner, token = owner[shared], np.unique(token[shared], return_inverse=True)[1]
    rows, cols = (np.flatnonzero(left), np.flatnonzero(~left)) if (~left).any() else (np.arange(len(sets)),) * 2
    both = np.zeros((len(rows), len(cols)), np.float32)
    place = np.argsort(token, kind="stable")
    owner, token = owner[place], token[place]
    for a in range(0, int(token[-1]) + 1 if len(token) else 0, columns):
        i, j = np.searchsorted(token, [a, a + columns])
        dense = np.zeros((len(sets), columns), np.float32)
        dense[owner[i:j], token[i:j] - a] = 1
        both += dense[rows] @ dense[cols].T
    both = both.astype(np.int64)
    x, y = np.nonzero(den * both >= num * (sizes[rows][:, None] + sizes[cols][None, :] - both))
    root = list(range(len(sets)))
    out = []
    for p, q in zip(rows[x].tolist(), cols[y].tolist(), strict=True):
        u, v = p, q
        while root[u] != u:
            root[u] = u = root[root[u]]
        while root[v] != v:
            root[v] = v = root[root[v]]
        if u != v:
            root[u] = v
            out.append((p, q))
    return out


def _cell_links(num: int, den: int):
    """Reads rows sorted by cell, holds one cell at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def links(rows: list[tuple]) -> pa.RecordBatch:
            ids = [r[0] for r in rows]
            found = linked([np.frombuffer(r[2], np.uint64) for r in rows], np.array([r[1] for r in rows]), num, den) if len(rows) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([ids[p[k]] for p in found], pa.int64()) for k in (0, 1)], ["a", "b"])

        now, rows = None, []
        for batch in batches:
            for *cell, id_, left, items in zip(*(batch.column(k).to_pylist() for k in range(6)), strict=True):
                if cell != now:
                    if rows:
                        yield links(rows)
                    now, rows = cell, []
                rows.append((id_, left, items))
        if rows:
            yield links(rows)

    return run


def near_duplicates(docs: DataFrame, size: int, num: int, den: int, block: int = 512) -> DataFrame:
    """doc_id, tk, set size and component_id of each document; sets link where den * common >= num * union."""
    signed = Stage(sketched(docs, size), "sketches").df
    classes = (
        signed.filter("n > 0")
        .groupBy("s1", "s2")
        .agg(F.min("doc_id").alias("least_doc"), F.min(F.struct("tk", "doc_id", "bands")).alias("own"))
        .select("s1", "s2", "least_doc", "own.*", F.monotonically_increasing_id().alias("id"))
    )
    classes = Stage(classes, "classes").df
    member = classes.select("id", F.explode("bands").alias("band"))
    centres = member.groupBy("band").agg(F.min("id").alias("centre"), F.count("*").alias("c")).filter("c > 1")
    star = member.join(Stage(centres, "centres").df, "band")  # read back, so that a very common band can be split
    family = components(star.filter("id <> centre").select("id", "centre"), "families")
    family = Stage(family.unionByName(family.select(F.col("root").alias("node"), "root").distinct()), "family").df

    # Each family in blocks of members; a member meets every block of its family once.
    blocks = family.groupBy("root").agg(F.ceil(F.count("*") / block).cast("int").alias("n_blocks"))
    sets = _sets_of(docs, family.join(classes, family["node"] == classes["id"]).select("id", "tk", "doc_id"), size)
    placed = sets.join(family, sets["id"] == family["node"]).join(blocks, "root").select("root", "id", "items", "n_blocks", F.pmod(F.xxhash64("id"), F.col("n_blocks")).cast("int").alias("own"))
    other = F.explode(F.sequence(F.lit(0), F.col("n_blocks") - 1)).alias("other")
    cells = placed.select("root", "id", "items", "own", other).select("root", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "id", "own", "items")
    cells = cells.select("root", "i", "j", "id", (F.col("own") == F.col("i")).alias("left"), "items").repartition("root", "i", "j").sortWithinPartitions("root", "i", "j", "id")
    links = cells.mapInArrow(_cell_links(num, den), "a long, b long")
    group = components(links, "links")

    group = classes.select("id", "s1", "s2", "least_doc").join(group, F.col("id") == F.col("node"), "left").select("s1", "s2", "least_doc", F.coalesce("root", "id").alias("root"))
    least = group.groupBy("root").agg(F.min("least_doc").alias("component_id"))
    named = group.join(least, "root").select("s1", "s2", "component_id")
    out = signed.select("doc_id", "tk", "n", "s1", "s2").join(named, ["s1", "s2"], "left")
    return out.select("doc_id", "tk", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def drop_near_duplicates(docs: DataFrame, size: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """Of each group the document with the least id, all columns unchanged.

    Rows that repeat that id and its text all stay, and so do all rows with a null doc_id, copies or not.
    """
    found = near_duplicates(docs, size, num, den)
    gone = found.filter("n_shingles > 0 AND doc_id <> component_id").select(F.col("doc_id").alias("_gk_doc"), F.col("tk").alias("_gk_gone")).distinct()
    keyed = docs.withColumn("_gk_tk", F.xxhash64(text_of()))
    return keyed.join(gone, (F.col("_gk_tk") == F.col("_gk_gone")) & (docs["doc_id"] == F.col("_gk_doc")), "left_anti").drop("_gk_tk")


def op3_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"), 3, 85, 100)
    return found.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


OP3_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 2], ' ') AS s FROM w, unnest(range(1, greatest(CAST(len(w) AS BIGINT) - 1, 2))) AS t(i) WHERE len(w) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS (SELECT x, y FROM c JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * c >= 85 * (a.n + b.n - c)),
reach(x, y) AS (SELECT doc_id, doc_id FROM w UNION SELECT r.x, e.y FROM reach r JOIN e ON r.y = e.x),
m AS (SELECT x, min(y) AS component_id FROM reach GROUP BY x)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, m.component_id, w.doc_id = m.component_id AS kept
FROM w LEFT JOIN n USING (doc_id) JOIN m ON m.x = w.doc_id
"""
