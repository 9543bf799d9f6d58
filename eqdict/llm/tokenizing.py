"""Token ids of whole texts, equal to those of the `tokenizers` library, per Python worker.

A byte-level BPE file is also loaded into tiktoken's engine, which is several times faster. It encodes a text only if each of its
characters is of a kind on which the two libraries' patterns are known to agree, and if no special string is in it; the
`tokenizers` library encodes every other text. Both engines are compared on probe strings when a worker loads them; a difference
turns the fast one off.
"""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import numpy as np

#: Characters that both engines split alike (checked one by one in the tests).
PLAIN = re.compile(r"[\x09-\x0d\x20-\x7e\xa0-ɏ‐-‧‰-⁞€]*")
#: Longest run that the fast engine gets, as a long run without a break is one piece of the pattern.
_RUN = re.compile(r"\S{4096}|\s{4096}")
_PROBES = ["", " ", "a  b\n\n c\t", "I'll we'VE don't 12 345,6!?  --x_y", "é ñandú Übergröße – “q” …", "\x0b\x0c\xa0\xa0x  y"]


class Encoder:
    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.slow = Tokenizer.from_file(path)
        self.special = [t.content for t in self.slow.get_added_tokens_decoder().values()]
        self.fast = self._fast()

    def _fast(self):
        import json

        import tiktoken

        spec = json.loads(self.slow.to_str())
        pre = spec.get("pre_tokenizer") or {}
        model = spec["model"]
        same = model["type"] == "BPE" and pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space")
        if not same or spec.get("normalizer") or any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges")):
            return None
        # the byte alphabet of byte-level BPE: printable bytes stand for themselves, the rest follow from 256 on
        shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
        byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(shown))}
        specials = set(self.special)
        ranks = {bytes(byte[c] for c in t): i for t, i in model["vocab"].items() if t not in specials}
        ids = [ranks[bytes(byte[c] for c in "".join(m if isinstance(m, list) else m.split(" ")))] for m in model["merges"]]
        if ids != sorted(ids):  # merge order must be id order
            return None
        import public_tokenizers

        engine = tiktoken.Encoding("fast", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        for p in _PROBES:
            if engine.encode_ordinary(p) != self.slow.encode(p, add_special_tokens=False).ids:
                return None
        return engine

    def ids(self, text: str) -> list[int]:
        if self.fast is not None and PLAIN.fullmatch(text) and not _RUN.search(text) and not any(s in text for s in self.special):
            return self.fast.encode_ordinary(text)
        return self.slow.encode(text, add_special_tokens=False).ids

    def array(self, text: str) -> np.ndarray:
        return np.array(self.ids(text), "<u4")


@lru_cache(maxsize=4)
def encoder(path: str) -> Encoder:
    return Encoder(path)


def file_digest(path: str) -> str:
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()
