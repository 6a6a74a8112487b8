"""Cost-balanced packing of documents into token sequences (operator 2).

A piece of n tokens costs ``linear * n + quadratic * n**2`` (the feed-forward and
the attention share). Documents longer than a sequence first give full sequences;
the rest is packed block by block: a block opens as many sequences as its tokens
fill, takes its pieces by descending cost and gives each to the cheapest sequence
that has room for it. A piece that fits nowhere is cut to fill the cheapest open
sequence. Tokens beyond whole sequences go on to the next block, and the last
ones of a task become sequences of power-of-two lengths, which need no padding.

Tasks pack their own scan split, so nothing is shuffled and no group can grow
hot; a retried task makes the same sequences again. Memory per task: one block.

Edge cases: a null text is empty (its one piece is the end id); a null doc_id
stays null; repeated rows are packed each; further columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from .base import table, text_of
from .encoder import encoder, tokenizer_path

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
NAMES = [c.split()[0] for c in SCHEMA.split(", ")]


def attention_cost(n, linear: float = 1.0, quadratic: float = 1 / 512):
    return linear * n + quadratic * n * n


class Packer:
    """Packs the pieces of one task. A piece: (doc_id, start, ids as bytes, tokens of its document)."""

    def __init__(self, capacity: int, first_id: int, block_tokens: int, cost=attention_cost):
        self.capacity, self.next_id, self.block_tokens, self.cost = capacity, first_id, max(block_tokens, capacity), cost
        self.rows: list[tuple] = []
        self.held: list[tuple] = []
        self.held_tokens = 0

    def _emit(self, piece: tuple, sequence: int, offset: int) -> None:
        doc, start, ids, total = piece
        self.rows.append((doc, start, len(ids) // 4, zlib.crc32(ids), total, sequence, offset))

    def add(self, doc: int | None, ids: bytes) -> None:
        total, full = len(ids) // 4, self.capacity * 4
        cut = len(ids) // full * full
        for at in range(0, cut, full):
            self._emit((doc, at // 4, ids[at : at + full], total), self.next_id, 0)
            self.next_id += 1
        if cut < len(ids):
            self.held.append((doc, cut // 4, ids[cut:], total))
            self.held_tokens += (len(ids) - cut) // 4
            if self.held_tokens >= self.block_tokens:
                self._block()

    def _block(self) -> None:
        n = self.held_tokens // self.capacity
        if not n:
            return
        cost, room, fill = np.zeros(n), np.full(n, self.capacity), np.zeros(n, np.int64)
        todo = sorted(self.held, key=lambda p: len(p[2]))
        left: list[tuple] = []
        while todo:
            piece = todo.pop()
            length = len(piece[2]) // 4
            fits = np.where(room >= length, cost, np.inf)
            k = int(np.argmin(fits))
            if fits[k] == np.inf:
                k = int(np.argmin(np.where(room > 0, cost, np.inf)))
                if not (part := int(room[k])):
                    left.append(piece)
                    continue
                doc, start, ids, total = piece
                left_over = (doc, start + part, ids[part * 4 :], total)
                piece, length = (doc, start, ids[: part * 4], total), part
                todo.append(left_over)
                todo[-2:] = sorted(todo[-2:], key=lambda p: len(p[2]))
            self._emit(piece, self.next_id + k, int(fill[k]))
            cost[k] += self.cost(length)
            room[k] -= length
            fill[k] += length
        self.next_id += n
        self.held, self.held_tokens = left, sum(len(p[2]) // 4 for p in left)

    def close(self) -> None:
        """Packs what is left; the last tokens fill sequences of falling powers of two."""
        self._block()
        tail, self.held = self.held, []
        while self.held_tokens:
            size = min(self.capacity, 1 << (self.held_tokens.bit_length() - 1))
            offset = 0
            while offset < size:
                doc, start, ids, total = tail.pop()
                part = min(len(ids) // 4, size - offset)
                self._emit((doc, start, ids[: part * 4], total), self.next_id, offset)
                if part * 4 < len(ids):
                    tail.append((doc, start + part, ids[part * 4 :], total))
                offset += part
            self.held_tokens -= size
            self.next_id += 1

    def take(self) -> pa.RecordBatch:
        columns = list(zip(*self.rows, strict=True)) or [()] * len(NAMES)
        self.rows = []
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], NAMES)


def pack_stream(docs: Iterable[tuple[int | None, bytes]], capacity: int, first_id: int, block_tokens: int = 1 << 20, emit_rows: int = 20_000) -> Iterator[pa.RecordBatch]:
    packer = Packer(capacity, first_id, block_tokens)
    for doc, ids in docs:
        packer.add(doc, ids)
        if len(packer.rows) >= emit_rows:
            yield packer.take()
    packer.close()
    if packer.rows:
        yield packer.take()


def pack_documents(docs: DataFrame, capacity: int = 2048, end_id: int = 1, tokenizer: str | None = None) -> DataFrame:
    """One row per piece; ``sequence_id`` is unique over the result."""
    path, end = tokenizer or tokenizer_path(), np.array([end_id], "<u4").tobytes()

    def run(batches):
        enc = encoder(path)

        def stream():
            for batch in batches:
                for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    yield doc, enc.ids(text.as_py()).tobytes() + end

        yield from pack_stream(stream(), capacity, TaskContext.get().partitionId() << 40)

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_of().alias("text")).mapInArrow(run, SCHEMA)


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
