"""Token counts by byte-pair merging, without making tokens.

A text is cut into the pieces that the vocabulary's pattern gives.  For each distinct piece the
bytes form a doubly linked list, a heap holds the adjacent pairs by rank, and the lowest pair is
merged again and again; the count is the number of bytes less the number of merges.  Workers keep
the counts of recent pieces, up to a fixed number, so a frequent piece is merged once.

Cases: null text counts as empty (0 bytes, 0 tokens); special strings inside a text are one token
each, as the library has it by default; null ids are kept; repeated rows are counted row by row.
"""

from __future__ import annotations

import heapq
import json

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from levelindex.llm.common import id_and_text, small_batches

#: Fixed value of the format: the byte-level splitting pattern of these vocabularies.
PIECES = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Most counts that a worker keeps. The first ones seen stay: frequent pieces turn up early.
KEPT_CHUNKS, KEPT_PIECES = 900_000, 300_000
#: A space next to other white space: there the text can't be cut by spaces alone.
BESIDE_SPACE = [p for c in map(chr, range(0x3001)) if c != " " and regex.match(r"\s", c) for p in (c + " ", " " + c)]

_loaded: dict[str, "PieceCounter"] = {}


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins that byte-level vocabulary files write for bytes."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class PieceCounter(dict):
    """Counts of text chunks between single spaces, filled on demand and bounded in number."""

    def __init__(self, file: str):
        super().__init__()
        spec = json.load(open(file, encoding="utf-8"))
        to_byte = byte_alphabet()
        raw = lambda s: bytes(to_byte[c] for c in s)
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in spec["model"]["merges"]]
        symbols: dict[bytes, int] = {bytes([b]): b for b in range(256)}
        # A pair of symbols, as one number, gives its order and the symbol made of it.
        self.order: dict[int, int] = {}
        self.made: dict[int, int] = {}
        for order, (left, right) in enumerate(pairs):
            a, b = raw(left), raw(right)
            pair = symbols[a] << 32 | symbols[b]
            if pair not in self.order:
                self.order[pair] = order
                self.made[pair] = symbols.setdefault(a + b, len(symbols))
        self.pieces: dict[str, int] = {}
        special = [t["content"] for t in spec.get("added_tokens", [])]
        self.special = regex.compile("|".join(regex.escape(s) for s in sorted(special, key=len, reverse=True))) if special else None
        self.pattern = regex.compile(PIECES)

    def merged(self, piece: bytes) -> int:
        """Symbols left of one piece after all merges."""
        left_over = n = len(piece)
        symbol, after, before = [*piece, -1], list(range(1, n + 2)), list(range(-1, n))
        order, made, push, pop = self.order, self.made, heapq.heappush, heapq.heappop
        heap = [found << 32 | i for i in range(n - 1) if (found := order.get(symbol[i] << 32 | symbol[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            top = pop(heap)
            i = top & 0xFFFFFFFF
            j = after[i]
            if symbol[i] < 0 or symbol[j] < 0 or order.get(pair := symbol[i] << 32 | symbol[j]) != top >> 32:
                continue  # one of the two has gone or changed since
            symbol[i], symbol[j] = new, _ = made[pair], -1
            after[i] = k = after[j]
            before[k] = i
            left_over -= 1
            if symbol[k] >= 0 and (found := order.get(new << 32 | symbol[k])) is not None:
                push(heap, found << 32 | i)
            h = before[i]
            if h >= 0 and (found := order.get(symbol[h] << 32 | new)) is not None:
                push(heap, found << 32 | h)
        return left_over

    def plain(self, text: str) -> int:
        total, pieces = 0, self.pieces
        for piece in self.pattern.findall(text):
            n = pieces.get(piece)
            if n is None:
                n = self.merged(piece.encode())
                if len(pieces) < KEPT_PIECES and len(piece) <= 32:
                    pieces[piece] = n
            total += n
        return total

    def __missing__(self, chunk: str) -> int:
        """A chunk that follows a single space, without white space at its ends."""
        if chunk.isalpha():
            n = self.pieces.get(piece := " " + chunk)
            if n is None:
                n = self.merged(piece.encode())
        else:
            n = self.plain(" " + chunk)
        if len(self) < KEPT_CHUNKS and len(chunk) <= 32:
            self[chunk] = n
        return n

    def section(self, text: str) -> int:
        """Tokens of a text without special strings.

        A single space between two characters that are not white space always begins a piece, so
        the text can be cut there; other white space is left to the pattern.
        """
        if not text:
            return 0
        chunks = text.split(" ")
        if "" in chunks or any(pair in text for pair in BESIDE_SPACE):
            return sum(self.plain(c) for c in regex.split(r"(?<=\S)(?= \S)", text))
        return self.plain(chunks[0]) + sum(map(self.__getitem__, chunks[1:]))

    def count(self, text: str) -> int:
        if self.special is None or not self.special.search(text):
            return self.section(text)
        found = len(self.special.findall(text))
        return found + sum(map(self.section, self.special.split(text)))


def counter(file: str) -> PieceCounter:
    if file not in _loaded:
        _loaded[file] = PieceCounter(file)
    return _loaded[file]


def vocabulary_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def token_counts(docs: DataFrame, vocabulary: str | None = None, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row of `docs`.

    `vocabulary` is the path of a byte-level BPE file on the workers; by default the installed one.
    """

    def run(batches):
        own = counter(vocabulary or vocabulary_path())
        for batch in small_batches(batches, "text"):
            texts = batch.column("text").to_pylist()
            counts = [own.count(t or "") for t in texts]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pa.array([len((t or "").encode()) for t in texts], pa.int64()),
                    pa.array(counts, pa.int64()),
                    pa.array([c > limit for c in counts], pa.bool_()),
                ],
                ["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    return id_and_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
