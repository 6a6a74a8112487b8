import random
import zlib
from collections import defaultdict

import numpy as np
import pytest
from tokenizers import Tokenizer

from graphkw.llm.encoder import TextEncoder, safe_parts, tokenizer_path
from graphkw.llm.packing import pack_documents
from graphkw.llm.token_counts import count_tokens
from tests.llm.conftest import ODD


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(tokenizer_path())


def test_encoder_equals_library(library):
    enc, draw = TextEncoder(tokenizer_path()), random.Random(3)
    parts = ["a", "B", "'s", "don't", " ", "  ", "\n", "é", "\x85", "\u3000", "\xa0", "<|endoftext|>", "12", "!!", "日本", "\u200b", "x " * 3, "😀", "—", "“q”"]
    for _ in range(3000):
        t = "".join(draw.choice(parts) for _ in range(draw.randint(0, 14)))
        assert enc.ids(t).tolist() == library.encode(t, add_special_tokens=False).ids, repr(t)
    for _ in range(100):
        t = "".join(draw.choice(parts) for _ in range(300))
        cut = safe_parts(t, 10)
        assert "".join(cut) == t
        assert sum((library.encode(p, add_special_tokens=False).ids for p in cut), []) == library.encode(t, add_special_tokens=False).ids


def test_counts_edge_cases(docs, library):
    got = sorted(map(tuple, count_tokens(docs(ODD), limit=5).collect()), key=str)
    want = []
    for i, t in ODD:
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        want.append((i, len((t or "").encode()), n, n > 5))
    assert got == sorted(want, key=str)
    assert count_tokens(docs([])).count() == 0


def test_packing_round_trip(docs, library):
    draw = random.Random(5)
    rows = ODD[:1] + [(k, " ".join(draw.choice(["the", "graph", "ßa", "<|endoftext|>"]) for _ in range(draw.randint(0, 3000)))) for k in range(10, 60)]
    pieces = pack_documents(docs(rows).coalesce(2), capacity=512).collect()
    want = {i: np.array([*library.encode(t or "", add_special_tokens=False).ids, 1], "<u4") for i, t in rows}
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for p in pieces:
        by_doc[p.doc_id].append(p)
        by_seq[p.sequence_id].append((p.offset, p.length))
    assert set(by_doc) == set(want)
    for i, ps in by_doc.items():
        at = 0
        for p in sorted(ps, key=lambda p: p.start):
            assert p.start == at and p.doc_tokens == len(want[i])
            assert p.ids_crc32 == zlib.crc32(want[i][at : at + p.length].tobytes())
            at += p.length
        assert at == len(want[i])
    for parts in by_seq.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 512 and at & (at - 1) == 0  # full, or a power of two: no padding


def test_packing_nulls(docs):
    got = pack_documents(docs(ODD)).collect()
    assert sum(p.doc_id is None for p in got) >= 2 and min(p.length for p in got) >= 1
    assert pack_documents(docs([])).count() == 0
