"""Exact encoding of whole texts in parts.

A byte-level BPE first splits a text into words and never merges across them. A
single space between two characters that are not white space always starts a new
word, so a text may be cut before it and the parts encoded alone, in batches.

Texts of characters that every version of Unicode classes alike go through a
second library with the very merges of the tokenizer's file, which gives the same
ids several times faster; all others, and texts with special strings, go through
the tokenizer's own library.
"""

from __future__ import annotations

import json
import os
import re
from functools import lru_cache
from itertools import chain

import numpy as np

DEFAULT_TOKENIZER = "byte_bpe_50k.json"
#: Texts are cut into parts of about so many characters.
PART_CHARS = 1 << 14
#: Latin letters, signs and punctuation of the first versions of Unicode.
_SETTLED = re.compile("[\\x00-\u0240\u2010-\u2027\u2030-\u203a\u20ac]*").fullmatch
#: Characters that any definition of white space may hold; a cut beside them is not taken.
_BLANK = frozenset(map(chr, chain(range(0x21), (0x7F, 0x85, 0xA0, 0x1680, 0x180E), range(0x2000, 0x2010), (0x2028, 0x2029, 0x202F, 0x205F, 0x2060, 0x3000, 0xFEFF))))


def tokenizer_path(name: str = DEFAULT_TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _merge_ranks(path: str) -> dict[bytes, int] | None:
    """Token bytes to ids where the file is a plain byte-level BPE whose merges are numbered in order; else None."""
    spec = json.loads(open(path, encoding="utf-8").read())
    model, pre = spec["model"], spec.get("pre_tokenizer") or {}
    if spec.get("normalizer") or model.get("type") != "BPE" or pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") or not pre.get("use_regex", True):
        return None
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    byte_of = {chr(b): b for b in plain} | {chr(0x100 + k): b for k, b in enumerate(b for b in range(256) if b not in plain)}
    added = {t["content"] for t in spec["added_tokens"]}
    vocab, merges = model["vocab"], [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
    merged = [vocab.get(a + b, -1) for a, b in merges]
    if merged != sorted(merged) or merged[:1] != [256] or model.get("ignore_merges") or any(vocab.get(c, 256) > 255 for c in byte_of):
        return None
    return {bytes(byte_of[c] for c in t): i for t, i in vocab.items() if t not in added}


def _clean(part: str) -> bool:
    return bool(part) and part[0] not in _BLANK and part[-1] not in _BLANK


def safe_parts(text: str, size: int = PART_CHARS) -> list[str]:
    """Cuts a text about every ``size`` characters, only before single spaces where no token can cross."""
    out, start = [], 0
    while len(text) - start > size:
        at = start + size
        while (at := text.find(" ", at)) >= 0 and not (at + 1 < len(text) and text[at - 1] not in _BLANK and text[at + 1] not in _BLANK):
            at += 1
        if at < 0:
            break
        out.append(text[start:at])
        start = at
    return [*out, text[start:]]


class TextEncoder:
    """Encodes whole texts as the tokenizer's library does by default, special strings in texts included."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library, self.quick = Tokenizer.from_file(path), None
        if ranks := _merge_ranks(path):
            import public_tokenizers
            import tiktoken

            self.quick = tiktoken.Encoding("parts", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_to_numpy
            self.specials = [t.content for t in self.library.get_added_tokens_decoder().values()]

    def ids(self, text: str) -> np.ndarray:
        """Unsigned little-endian 32-bit ids."""
        if not text:
            return np.empty(0, "<u4")
        if self._quickly(text):
            return np.concatenate([self.quick(p, disallowed_special=()) for p in safe_parts(text)]).astype("<u4", copy=False)
        return np.concatenate([np.array(e.ids, "<u4") for e in self.library.encode_batch_fast(safe_parts(text), add_special_tokens=False)])

    def _quickly(self, text: str) -> bool:
        return bool(self.quick and _SETTLED(text) and not any(s in text for s in self.specials))

    def lengths(self, texts: list[str]) -> list[int]:
        """The number of ids of each text; what the tokenizer's own library encodes goes to it as one batch."""
        counts, owner, parts = [0] * len(texts), [], []
        for i, text in enumerate(texts):
            if self._quickly(text):
                counts[i] = sum(len(self.quick(p, disallowed_special=())) for p in safe_parts(text))
            elif text:
                pieces = safe_parts(text)
                owner += [i] * len(pieces)
                parts += pieces
        for i, e in zip(owner, self.library.encode_batch_fast(parts, add_special_tokens=False), strict=True):
            counts[i] += len(e.ids)
        return counts


@lru_cache(maxsize=2)
def encoder(path: str) -> TextEncoder:
    """One encoder for each worker process and vocabulary."""
    return TextEncoder(path)
