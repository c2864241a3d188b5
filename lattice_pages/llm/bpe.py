"""BPE encoding and decoding with a contiguous rank array.

A short word is a list of part boundaries and a parallel list with the rank of the
merge at each boundary. Encoding scans that list for its minimum, deletes the boundary
and refreshes the two neighbouring ranks, until no merge is left. Words beyond
``LONG_WORD`` symbols use the same rule with a heap, so that no input costs a square.

Texts are cut at white space first (the vocabulary drops it), so a chunk between two
blanks has the same ids wherever it stands; a bounded cache holds them per worker.

Defined results: a null text counts as empty (no ids, empty decoded text); repeated
rows give repeated results; an empty table gives an empty table. ``encode_decode``
reads the id and text columns only, so any other column is let through by a join of
the caller and cannot clash. Whole texts are processed, however long.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import struct
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

#: Unicode White_Space, spelt out: str.split() would also cut at U+001C..U+001F.
WHITE = "\t-\r \x85\xa0  -     　"
LONG_WORD = 256
CACHE_ENTRIES = 300_000


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {b: chr(b) for b in plain}
    rest = [b for b in range(256) if b not in table]
    table.update({b: chr(256 + i) for i, b in enumerate(rest)})
    return [table[b] for b in range(256)]


def merge_short(ids: list[int], merges: dict[tuple[int, int], tuple[int, int]]) -> list[int]:
    """Ids after all merges of one short word; ``merges``: pair -> (rank, merged id)."""
    none = (1 << 60, -1)
    look = merges.get
    parts = list(ids)
    at = [look(p, none) for p in zip(parts, parts[1:])]
    while at:
        best = min(at)
        if best[1] < 0:
            break
        i = at.index(best)
        parts[i] = best[1]
        del parts[i + 1], at[i]
        if i < len(at):
            at[i] = look((parts[i], parts[i + 1]), none)
        if i:
            at[i - 1] = look((parts[i - 1], parts[i]), none)
    return parts


def merge_long(ids: list[int], merges: dict[tuple[int, int], tuple[int, int]]) -> list[int]:
    """The same result in n log n for words of any length: linked parts and a heap."""
    parts: list[int | None] = list(ids)
    n = len(parts)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(*m, i, parts[i], parts[i + 1]) for i in range(n - 1) if (m := merges.get((parts[i], parts[i + 1])))]
    heap = [(rank, i, new, a, b) for rank, new, i, a, b in heap]
    heapq.heapify(heap)
    while heap:
        _, i, new, a, b = heapq.heappop(heap)
        j = after[i]
        if parts[i] != a or j >= n or parts[j] != b:
            continue
        parts[i], parts[j] = new, None
        after[i] = after[j]
        if after[i] < n:
            before[after[i]] = i
        for x in (before[i], i):
            y = after[x] if x >= 0 else n
            if y < n and (m := merges.get((parts[x], parts[y]))):
                heapq.heappush(heap, (m[0], x, m[1], parts[x], parts[y]))
    return [p for p in parts if p is not None]


class WordBpe:
    """Encoder and decoder for a vocabulary file of the word-end kind."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.token_of = {i: t for t, i in self.vocab.items()}
        self.end = model.get("end_of_word_suffix") or ""
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.token_of.update({i: t for t, i in self.special.items()})
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, m in enumerate(model["merges"]):
            a, b = m if isinstance(m, list) else m.split(" ")
            self.merges.setdefault((self.vocab[a], self.vocab[b]), (rank, self.vocab[a + b]))
        self.bytes = byte_alphabet()
        self.pieces = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[\p{{L}}]+|[\p{{N}}]|[^{WHITE}\p{{L}}\p{{N}}]+")
        self.blank = regex.compile(f"[{WHITE}]+")
        self.split_special = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.words: dict[str, list[int]] = {}
        self.chunks = _Chunks(self)

    def word(self, piece: str) -> list[int]:
        got = self.words.get(piece)
        if got is None:
            marks = [self.bytes[b] for b in piece.encode("utf-8")]
            marks[-1] += self.end
            ids = [self.vocab[m] for m in marks if m in self.vocab]
            got = (merge_short if len(ids) <= LONG_WORD else merge_long)(ids, self.merges)
            if len(self.words) >= CACHE_ENTRIES:
                self.words.clear()
            if len(piece) <= 32:
                self.words[piece] = got
        return got

    def normal(self, text: str) -> str:
        if not unicodedata.is_normalized("NFC", text):
            text = unicodedata.normalize("NFC", text)
        return "".join(c.lower() for c in text) if "Σ" in text else text.lower()  # no final sigma

    def chunks_of(self, text: str) -> list[str]:
        text = self.normal(text)
        if any(c in text for c in "\x1c\x1d\x1e\x1f"):
            return [c for c in self.blank.split(text) if c]
        return text.split()

    def encode_text(self, text: str) -> tuple[bytes, str]:
        """Ids as little-endian unsigned 32-bit integers, and the text they decode to."""
        chunks = self.chunks
        if self.split_special is not None and "<|" in text:
            got = []
            for part in self.split_special.split(text):
                if part in self.special:
                    got.append((struct.pack("<I", self.special[part]), part))
                else:
                    got += [chunks[c] for c in self.chunks_of(part)]
        else:
            got = [chunks[c] for c in self.chunks_of(text)]
        return b"".join([g[0] for g in got]), " ".join([g[1] for g in got if g[0]])

    def encode(self, text: str) -> list[int]:
        raw = self.encode_text(text)[0]
        return list(struct.unpack(f"<{len(raw) // 4}I", raw))

    def decode(self, ids: list[int]) -> str:
        """Tokens joined by blanks: the vocabulary names no decoder of its own."""
        return " ".join(self.token_of[i] for i in ids if i in self.token_of)


class _Chunks(dict):
    """Chunk -> (ids as bytes, decoded text); bounded, filled on a miss."""

    def __init__(self, bpe: WordBpe) -> None:
        super().__init__()
        self.bpe = bpe

    def __missing__(self, chunk: str) -> tuple[bytes, str]:
        ids = [i for w in self.bpe.pieces.findall(chunk) for i in self.bpe.word(w)]
        got = (struct.pack(f"<{len(ids)}I", *ids), self.bpe.decode(ids))
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        if len(chunk) <= 64:
            self[chunk] = got
        return got


def encode_decode(docs: DataFrame, vocab_path: str, id_col: str = "doc_id", text_col: str = "text", keep_output: bool = False) -> DataFrame:
    """Encode every text, decode the ids again; one row per document.

    ``keep_output`` adds the ids themselves (``ids``) and the decoded text (``decoded``).
    Map-only: one pass over two columns, no shuffle.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    cols = [(id_col, None), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())]
    ddl = f"`{id_col}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string"
    if keep_output:
        ddl += ", ids binary, decoded string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = None
        for b in batches:
            bpe = bpe or WordBpe(vocab_path)
            out: list[tuple] = []
            for text in b.column(1):
                raw, decoded = bpe.encode_text(text.as_py() or "")
                row = (len(raw) // 4, hashlib.sha256(raw).hexdigest(), hashlib.sha256(decoded.encode("utf-8")).hexdigest())
                out.append(row + ((raw, decoded) if keep_output else ()))
            arrays = [b.column(0)] + [pa.array([r[i] for r in out], t) for i, (_, t) in enumerate(cols[1:])]
            names = [c for c, _ in cols]
            if keep_output:
                arrays += [pa.array([r[3] for r in out], pa.binary()), pa.array([r[4] for r in out], pa.string())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(arrays, names)

    return docs.select(id_col, text_col).mapInArrow(run, ddl)
