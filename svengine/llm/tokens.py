"""Byte-pair encoding with forced boundaries, shared by the operators that need token ids.

A byte pair that occurs inside no vocabulary token can't be merged across, so a cut between its bytes is certain. Texts are cut at every
such pair, inside pre-tokens as well as between them; each fragment is encoded by itself and the ids are concatenated.

A cut must not change how the tokenizer's pattern splits either side. Both sides keep their pre-tokens (or the rest of one) unless
the left side ends in white space, whose run the pattern splits by what follows, or the right side begins with an apostrophe inside a
run of marks, where a contraction would be seen that the whole text doesn't have. Such pairs, and pairs inside a character, aren't cut.

Fragments are mostly single words and repeat, so each worker keeps a bounded table of fragments and their packed ids.
"""

from __future__ import annotations

import array
import functools
import itertools
import json
import re

import numpy as np
import public_tokenizers
import tiktoken

DEFAULT = public_tokenizers.path("byte_bpe_50k.json")
#: White space of the tokenizer's pattern outside ASCII (the Unicode property), fixed values.
WIDE = "".join(map(chr, (0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)))
#: Fragments that a worker keeps at most, and bytes of the longest of them: an entry is below 330 bytes with its ids, so the table is below 40 MB.
KEPT, KEPT_KEY = 120_000, 32
#: Fragments that are looked up at once, which bounds the memory that a very long text takes.
STEP = 1 << 16


def _bytes_of_chars() -> dict[str, int]:
    """The byte that each printable stand-in of a byte-level vocabulary means: printable Latin-1 stands for itself, the rest follow from 256."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class ForcedBoundaryCodec:
    """encode() gives packed little-endian uint32 ids, as the tokenizers library does; decode() the text."""

    def __init__(self, path: str = DEFAULT):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        stand = _bytes_of_chars()
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(stand[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in self.special}
        self.token = [b""] * (max([*ranks.values(), *self.special.values()], default=-1) + 1)
        for b, i in ranks.items():
            self.token[i] = b
        for s, i in self.special.items():
            self.token[i] = s.encode()
        inside = np.zeros((256, 256), bool)
        for b in ranks:
            if len(b) > 1:
                a = np.frombuffer(b, np.uint8)
                inside[a[:-1], a[1:]] = True
        self.cut = self._cuts(inside)
        self.core = tiktoken.Encoding("forced", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})._core_bpe
        self.apart = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.kept: dict[bytes, bytes] = {}

    @staticmethod
    def _cuts(inside: np.ndarray) -> np.ndarray:
        """Whether a cut between two bytes is certain."""
        cut = ~inside
        cut[[*b"\t\n\x0b\x0c\r\x1c\x1d\x1e\x1f ", *{c.encode()[-1] for c in WIDE}]] = False
        cut[:, 0x80:0xC0] = False  # inside a character
        words = [b for b in range(128) if chr(b).isalnum()]
        cut[np.setdiff1d(np.arange(256), words), ord("'")] = False
        return cut

    def _fragment(self, b: bytes) -> bytes:
        packed = array.array("I", self.core.encode_ordinary(b.decode())).tobytes()
        if len(b) <= KEPT_KEY:
            if len(self.kept) >= KEPT:
                self.kept.clear()
            self.kept[b] = packed
        return packed

    def _plain(self, text: str) -> bytes:
        b = text.encode()
        a = np.frombuffer(b, np.uint8)
        get, one, out = self.kept.get, self._fragment, []
        at = np.flatnonzero(self.cut[a[:-1], a[1:]]) + 1
        for k in range(0, len(at) + 1, STEP):
            edges = [int(at[k - 1]) if k else 0, *at[k : k + STEP].tolist()]
            if k + STEP > len(at):
                edges.append(len(b))
            out += [get(s := b[i:j]) or one(s) for i, j in itertools.pairwise(edges)]
        return b"".join(out)

    def encode(self, text: str) -> bytes:
        if not text:
            return b""
        if not self.apart or not self.apart.search(text):
            return self._plain(text)
        ids = lambda s: np.array([self.special[s]], "<u4").tobytes() if s in self.special else self._plain(s)
        return b"".join(ids(s) for s in self.apart.split(text) if s)

    def decode(self, packed: bytes) -> str:
        token = self.token
        return b"".join([token[i] for i in np.frombuffer(packed, "<u4").tolist()]).decode("utf-8", "replace")


@functools.lru_cache(maxsize=1)
def codec(path: str = DEFAULT) -> ForcedBoundaryCodec:
    """One per worker process."""
    return ForcedBoundaryCodec(path)
