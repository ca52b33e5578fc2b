"""Tokenizer access for Python workers: whole texts through the public library, memoised by space-separated pieces.

Both vocabularies are additive over pieces that begin at a single space between two characters that aren't white
space: no match of either pre-tokenizer, and no composition of the normaliser, reaches over such a place. A piece is
encoded by the library once and looked up afterwards; the memo is bounded and belongs to one worker process.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from itertools import repeat

import numpy as np

MEMO_ITEMS = 400_000
#: Longer pieces are encoded each time; they hardly repeat.
MEMO_CHARS = 64
_SPACES = re.compile(r"\s\s|^\s|\s$")


def pieces(text: str) -> list[str]:
    """Parts of the text, each but the first with its leading space; their encodings join to that of the text."""
    parts = text.split(" ")
    if not _SPACES.search(text):
        return [parts[0], *map("".join, zip(repeat(" "), parts[1:]))]
    out, cur = [], parts[0]
    for p in parts[1:]:
        if cur and p and not cur[-1].isspace() and not p[0].isspace():
            out.append(cur)
            cur = " " + p
        else:
            cur += " " + p
    return [*out, cur]


class PieceTokenizer:
    """Encodes texts with one vocabulary file of the tokenizers library: no special tokens added, nothing cut or padded."""

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.ids: dict[str, bytes] = {}
        self.counts: dict[str, int] = {}

    def whole(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def _misses(self, parts: list[str], memo: dict, value) -> dict:
        new = list({p for p in parts if p not in memo})
        own = {p: value(e.ids) for p, e in zip(new, self.library.encode_batch_fast(new, add_special_tokens=False), strict=True)}
        for p, v in own.items():
            if len(memo) >= MEMO_ITEMS:
                break
            if len(p) <= MEMO_CHARS:
                memo[p] = v
        return own

    def _look_up(self, texts: list[str], memo: dict, value) -> list[list]:
        split = [pieces(t) for t in texts]
        own = self._misses([p for parts in split for p in parts], memo, value)
        return [[memo[p] if p in memo else own[p] for p in parts] for parts in split]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        return [b"".join(x) for x in self._look_up(texts, self.ids, lambda ids: np.array(ids, dtype="<u4").tobytes())]

    def count(self, texts: list[str]) -> list[int]:
        return [sum(x) for x in self._look_up(texts, self.counts, len)]


#: Longer runs of characters, or of white space, go to the tokenizers library.
RUN_CHARS, RUN_SPACES = 4000, re.compile(r"\s{400}")


class ByteLevelTokenizer(PieceTokenizer):
    """The same for a byte-level BPE whose ids follow the order of its merges: then merging by rank is merging by id.

    Such a vocabulary, read from the same file, is run by tiktoken's merge loop, several times as fast as the library.
    Anything else, and texts with special strings or extreme runs, takes the library's own way.
    """

    def __init__(self, path: str) -> None:
        super().__init__(path)
        self.fast = None
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, pre = spec["model"], spec["pre_tokenizer"] or {}
        self.special = [t["content"] for t in spec["added_tokens"]]
        plain = not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "ignore_merges"))
        if spec["normalizer"] or pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") or not pre.get("use_regex") or not plain:
            return
        merges = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        if any(model["vocab"]["".join(m)] != 256 + i for i, m in enumerate(merges)):
            return
        import public_tokenizers
        import tiktoken

        to_byte = _byte_of_char()
        ranks = {bytes(map(to_byte.__getitem__, token)): i for token, i in model["vocab"].items() if token not in self.special}
        self.fast = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def _plain(self, text: str) -> bool:
        return self.fast is not None and not any(s in text for s in self.special) and not RUN_SPACES.search(text) and max(map(len, text.split()), default=0) < RUN_CHARS

    def encode(self, texts: list[str]) -> list[bytes]:
        return [np.array(self.fast.encode_ordinary(t), dtype="<u4").tobytes() if self._plain(t) else self.whole(t) for t in texts]

    def count(self, texts: list[str]) -> list[int]:
        return [len(x) // 4 for x in self.encode(texts)]


def _byte_of_char() -> dict[str, int]:
    """Printable bytes stand for themselves in a byte-level vocabulary; the others follow from code point 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


_OPEN: dict[tuple, PieceTokenizer] = {}


def tokenizer(path: str, kind: type[PieceTokenizer] = PieceTokenizer) -> PieceTokenizer:
    """The worker's own tokenizer for this file."""
    if (path, kind) not in _OPEN:
        _OPEN[path, kind] = kind(path)
    return _OPEN[path, kind]


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def in_slices(texts: list[str], chars: int = 1 << 21) -> list[tuple[int, int]]:
    """Bounds of runs of texts with about so many characters, so that memory follows one run."""
    out, start, held = [], 0, 0
    for i, t in enumerate(texts):
        held += len(t)
        if held >= chars:
            out.append((start, i + 1))
            start, held = i + 1, 0
    return [*out, (start, len(texts))] if start < len(texts) else out


def crc(ids: bytes) -> int:
    return zlib.crc32(ids)
