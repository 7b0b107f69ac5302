"""Byte-level BPE ids, fast: pieces between blanks are encoded once and kept in a memo of bounded size.

The pre-tokenizer always starts a new piece at a blank that a non-blank follows. So a text is cut there, each cut piece
(with its leading blank) is encoded alone, and the ids are those of the whole text. A text where a blank is followed by
white space or by the end has other rules; it is encoded whole.

The vocabulary's added tokens (the end-of-text mark) are cut out of a text first, wherever their strings occur in it,
and stand for their own ids, as the ``tokenizers`` library has it by default. With ``marks=False`` their strings are
ordinary text.
"""

from __future__ import annotations

import base64
import json
import re
from array import array

MEMO = 400_000


def rank_file(path: str | None = None) -> str:
    """The vocabulary as ranks; by default the public 50k byte-level one, looked up where the code runs."""
    if path:
        return path
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


class _Memo(dict):
    """Ids of a blank and the piece after it, as little-endian 32-bit words."""

    def __init__(self, encode):
        super().__init__()
        self.encode = encode

    def __missing__(self, piece: str) -> bytes:
        if not piece or piece[0].isspace():
            raise KeyError(piece)
        if len(self) >= MEMO:
            self.clear()
        ids = self[piece] = array("I", self.encode(" " + piece)).tobytes()
        return ids


def marks_of(path: str | None = None) -> dict[str, int]:
    """The added tokens of the vocabulary and their ids, from its description in JSON."""
    if not path:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as f:
        return {t["content"]: t["id"] for t in json.load(f)["added_tokens"]}


class Encoder:
    def __init__(self, path: str | None = None, marks: bool = True):
        import public_tokenizers
        import tiktoken

        with open(rank_file(path), "rb") as f:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
        coding = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.plain = coding.encode_ordinary
        self.memo = _Memo(self.plain)
        self.marks = marks_of() if marks else {}
        self.mark = re.compile("(" + "|".join(map(re.escape, sorted(self.marks, key=len, reverse=True))) + ")") if self.marks else None

    def cut(self, text: str) -> list[str]:
        """The text at its marks: ordinary parts at even places, marks at odd ones."""
        return self.mark.split(text) if self.mark and any(m in text for m in self.marks) else [text]

    def ids(self, text: str) -> bytes:
        """The ids of a text as little-endian 32-bit words."""
        parts = self.cut(text)
        if len(parts) == 1:
            return self._ids(text)
        return b"".join(array("I", [self.marks[p]]).tobytes() if i % 2 else self._ids(p) for i, p in enumerate(parts))

    def _ids(self, text: str) -> bytes:
        if not text:
            return b""
        head, *rest = text.split(" ")
        try:
            tail = b"".join(map(self.memo.__getitem__, rest))
        except KeyError:
            return array("I", self.plain(text)).tobytes()
        return array("I", self.plain(head)).tobytes() + tail

    def count(self, text: str) -> int:
        return len(self.ids(text)) // 4


_ENCODERS: dict[str | None, Encoder] = {}


def encoder(path: str | None = None) -> Encoder:
    """One encoder a Python worker."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]
