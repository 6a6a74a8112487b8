"""Token counts of whole texts (operator 9).

Arrow batches are cut into runs of about equal bytes and encoded; only lengths
leave the worker. Long texts are split where no token can cross (see
:mod:`encoder`). No shuffle: one pass over the scan.

Edge cases: a null or empty text has 0 bytes and 0 tokens; a null ``doc_id``
stays null; repeated rows are counted each; further columns are ignored; an empty
table gives no rows; special strings inside texts count as the library counts
them (one token).
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .base import by_bytes, map_batches, table, text_of
from .encoder import encoder, tokenizer_path

SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"


def count_tokens(docs: DataFrame, limit: int = 1024, tokenizer: str | None = None, run_bytes: int = 1 << 20) -> DataFrame:
    """One row per document: bytes, tokens and whether it has more than ``limit`` tokens."""
    path = tokenizer or tokenizer_path()

    def make():
        enc = encoder(path)

        def work(batch):
            ids, texts = batch.column(0), batch.column(1).to_pylist()
            for a, b in by_bytes(texts, run_bytes):
                n_bytes = [len(t.encode("utf-8", "surrogatepass")) for t in texts[a:b]]
                n_tokens = enc.lengths(texts[a:b])
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(a, b - a), pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), pa.array([n > limit for n in n_tokens])],
                    ["doc_id", "n_bytes", "n_tokens", "over_limit"],
                )

        return work

    return map_batches(docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of().alias("text")), make, SCHEMA)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"))
