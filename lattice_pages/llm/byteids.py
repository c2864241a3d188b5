"""Token ids of a byte-level vocabulary, chunk by chunk.

A text without two blanks in a row falls apart at its blanks: each later chunk takes
one blank with it and has the same ids wherever it stands. Workers keep a bounded cache
of chunk -> ids; the rest of the work is a join of byte strings.
"""

from __future__ import annotations

import base64
import json
import re
import struct


class ByteIds(dict):
    """``ids(text)``: ids as little-endian unsigned 32-bit integers."""

    ENTRIES = 400_000

    def __init__(self, path: str) -> None:
        super().__init__()
        import tiktoken

        ranks, self.special = self._load(path)
        pattern = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
        self.coder = tiktoken.Encoding("byte-level", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.cut = re.compile("(" + "|".join(map(re.escape, self.special)) + ")") if self.special else None

    @staticmethod
    def _load(path: str) -> tuple[dict[bytes, int], dict[str, int]]:
        """Ranks by token bytes and special tokens of a ``tokenizers`` file or a rank file."""
        if not path.endswith(".json"):
            with open(path, "rb") as f:
                return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}, {}
        from lattice_pages.llm.bpe import byte_alphabet

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        back = {c: b for b, c in enumerate(byte_alphabet())}
        return {bytes(back[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in special}, special

    def _plain(self, text: str) -> bytes:
        ids = self.coder.encode_ordinary(text)
        return struct.pack(f"<{len(ids)}I", *ids)

    def __missing__(self, chunk: str) -> bytes:
        got = self._plain(" " + chunk)
        if len(self) >= self.ENTRIES:
            self.clear()
        if len(chunk) <= 64:
            self[chunk] = got
        return got

    def _part(self, text: str) -> bytes:
        if not text:
            return b""
        if "  " in text:
            return self._plain(text)
        first, *rest = text.split(" ")
        return (self._plain(first) if first else b"") + b"".join(map(self.__getitem__, rest))

    def ids(self, text: str) -> bytes:
        if self.cut is None or not any(s in text for s in self.special):
            return self._part(text)
        return b"".join(struct.pack("<I", self.special[p]) if p in self.special else self._part(p) for p in self.cut.split(text))
