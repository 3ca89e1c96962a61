"""Benchmark decontamination: rare n-gram seeds, then Smith-Waterman alignment.

Test items come in blocks of at most `block_words` words, so what a worker holds is bounded however
many items there are; every block meets all documents.  Seeds are the items' word n-grams.  A first
pass counts in how many documents each seed occurs; an item's seeds that are far more common than
its typical one (`common` times the median of those that occur) are its common ones.  A second pass
takes the stretch of the document around each chain of hits, and aligns it with the item word by
word: a match counts 1, a mismatch or gap -1.  A stretch with common seeds only is passed over if
it shares too few words with the item, in any order, to reach the least ratio: no alignment scores
more than the words shared, so this loses nothing.  The ratio of the best score to the item's
length tells copies with edits, insertions and deletions from chance hits.

Cases: null and empty texts match nothing; items without words are left out; items shorter than a
seed are their own seed and must occur whole; null keys are kept; repeated rows and repeated items
give rows of their own.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex.llm.common import LOWER_TABLE, id_and_text, map_rows, raw_texts, small_batches

EDGE = b".,;:!?\"'()[]{}<>|#$%&*-_/\\+=~`^@"
FOUND = "doc_id long, item_id long, ratio double, matched int, item_words int, begin_word int, end_word int"


@dataclass(frozen=True)
class AlignSettings:
    seed: int = 4
    common: float = 8.0
    least_ratio: float = 0.5
    block_words: int = 200_000


def words_of(text: bytes) -> list[bytes]:
    return [w for t in text.translate(LOWER_TABLE).split() if (w := t.strip(EDGE))]


class ItemBlock:
    """Items of one block: word numbers, seeds and where they stand."""

    def __init__(self, items: list[tuple[int, bytes]], s: AlignSettings):
        self.s = s
        self.vocabulary: dict[bytes, int] = {}
        self.names, self.words = [], []
        for name, text in items:
            if words := words_of(text):
                self.names.append(name)
                self.words.append(np.array([self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words], np.int64))
        self.bags = [np.unique(w, return_counts=True) for w in self.words]
        self.lengths = sorted({min(s.seed, len(w)) for w in self.words})
        self.seeds: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = {}
        at = 0
        for n in self.lengths:
            mine = [i for i, w in enumerate(self.words) if min(s.seed, len(w)) == n]
            code = np.concatenate([self.grams(self.words[i], n) for i in mine])
            item = np.concatenate([np.full(len(self.words[i]) - n + 1, i) for i in mine])
            order = np.argsort(code, kind="stable")
            values, begins = np.unique(code[order], return_index=True)
            self.seeds[n] = (values, np.append(begins, len(code)), item[order], np.arange(at, at + len(values)))
            at += len(values)
        self.n_seeds = at
        self.rare: np.ndarray | None = None

    @staticmethod
    def grams(words: np.ndarray, n: int) -> np.ndarray:
        """Hashes of the n-grams; those with unknown words (-1) come out as 0."""
        m = len(words) - n + 1
        if m <= 0:
            return np.zeros(0, np.uint64)
        h, known = np.zeros(m, np.uint64), np.ones(m, bool)
        with np.errstate(over="ignore"):
            for i in range(n):
                part = words[i : i + m]
                known &= part >= 0
                h = (h ^ (part.astype(np.uint64) + np.uint64(1))) * np.uint64(0x9E3779B97F4A7C15)
                h ^= h >> np.uint64(29)
        return np.where(known, h | np.uint64(1), np.uint64(0))

    def number(self, text: bytes) -> np.ndarray:
        get = self.vocabulary.get
        words = words_of(text)
        return np.fromiter((get(w, -1) for w in words), np.int64, len(words))

    def hits(self, words: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Positions in the document and places in the seed table."""
        values = self.seeds[n][0]
        code = self.grams(words, n)
        at = np.minimum(np.searchsorted(values, code), len(values) - 1)
        where = np.flatnonzero((values[at] == code) & (code != 0))
        return where, at[where]

    def keep_rare(self, documents: np.ndarray) -> None:
        """Mark, for each item, the seeds that are not far more common than the median of those that occur."""
        self.rare = []
        for n in self.lengths:
            values, begins, item, ids = self.seeds[n]
            entry = np.repeat(np.arange(len(values)), np.diff(begins))
            df = documents[ids[entry]]
            order = np.lexsort((df, item))
            edges = np.flatnonzero(np.concatenate(([True], item[order][1:] != item[order][:-1])))
            size = np.diff(np.append(edges, len(order)))
            absent = np.add.reduceat((df[order] == 0).astype(np.int64), edges)
            middle = edges + np.minimum(absent + np.maximum(size - absent - 1, 0) // 2, size - 1)
            median = np.repeat(df[order][middle], size)
            keep = np.zeros(len(item), bool)
            keep[order] = df[order] <= np.maximum(median * self.s.common, median)
            self.rare.append(keep)

    def shared(self, i: int, text: np.ndarray) -> int:
        """Words that item and text have in common, repeats included: no alignment scores more."""
        values, often = self.bags[i]
        at = np.minimum(np.searchsorted(values, text), len(values) - 1)
        return int(np.minimum(np.bincount(at[values[at] == text], minlength=len(values)), often).sum())

    def matches(self, words: np.ndarray):
        """item, ratio, matched words and place of the best alignment of each item with a seed here."""
        pairs = []
        for n, rare in zip(self.lengths, self.rare):
            where, at = self.hits(words, n)
            if not len(where):
                continue
            _, begins, item, _ = self.seeds[n]
            count = begins[at + 1] - begins[at]
            entry = np.repeat(begins[at] - (np.cumsum(count) - count), count) + np.arange(count.sum())
            place = np.repeat(where, count)
            pairs.append((item[entry], place, np.full(len(entry), n), rare[entry]))
        if not pairs:
            return
        item, place, n, rare = (np.concatenate([p[i] for p in pairs]) for i in range(4))
        order = np.lexsort((place, item))
        item, place, n, rare = item[order], place[order], n[order], rare[order]
        length = np.array([len(w) for w in self.words])[item]
        new = np.concatenate(([True], (item[1:] != item[:-1]) | (place[1:] - place[:-1] > length[1:])))[: len(item)]
        edges = np.append(np.flatnonzero(new), len(item))
        best: dict[int, tuple] = {}
        for a, b in zip(edges, edges[1:]):
            i, size = int(item[a]), int(length[a])
            low, high = max(0, int(place[a]) - size), min(len(words), int(place[b - 1] + n[b - 1]) + size)
            if not rare[a:b].any() and self.shared(i, words[low:high]) < self.s.least_ratio * size:
                continue
            score, matched, x, y = align(self.words[i], words[low:high])
            if score / size >= self.s.least_ratio and (i not in best or score > best[i][0]):
                best[i] = (score, matched, low + x, low + y)
        for i, (score, matched, x, y) in best.items():
            yield self.names[i], score / len(self.words[i]), matched, len(self.words[i]), x, y


def best_end(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int, int]:
    """Score and matched words of the best local alignment, and how far it reaches into item and text.

    Row by row over the item, gaps along the text by a running maximum; only one row is held.  A cell
    is score * unit + matched words, so that of equal scores the one with more matches wins.
    """
    n, unit = len(text), len(item) + 1
    row, steps = np.zeros(n + 1, np.int64), np.arange(n + 1, dtype=np.int64) * unit
    best, x, y = 0, 0, 0
    for i, word in enumerate(item.tolist(), 1):
        new = np.zeros(n + 1, np.int64)
        np.maximum(row[:-1] + np.where(text == word, unit + 1, -unit), row[1:] - unit, out=new[1:])
        # below one unit nothing is left of a score: the alignment begins anew
        new[new < unit] = 0
        row = np.maximum.accumulate(new + steps) - steps
        row[row < unit] = 0
        j = int(row.argmax())
        if row[j] > best:
            best, x, y = int(row[j]), i, j
    return best // unit, best % unit, x, y


def align(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int, int]:
    """Best local alignment: score, matched words, first and last place in the text (half open).

    The begin comes from the same pass over what lies before the end, read backwards; memory is one row.
    """
    score, matched, x, y = best_end(item, text)
    if not score:
        return 0, 0, 0, 0
    back = best_end(item[:x][::-1], text[:y][::-1])
    return score, matched, y - back[3], y


def item_blocks(items: DataFrame, s: AlignSettings, id_col: str, text_col: str):
    """Blocks of items on the driver, one at a time, each of about `block_words` words at most."""
    rows = id_and_text(items, id_col, text_col)
    total = rows.agg(F.coalesce(F.sum(F.size(F.split("text", r"\s+"))), F.lit(0))).first()[0]
    n = max(1, -(-total // s.block_words))
    for i in range(n):
        part = rows.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(n)) == i).orderBy("doc_id", "text")
        block = ItemBlock([(r.doc_id, r.text.encode()) for r in part.toLocalIterator()], s)
        if block.words:
            yield block


def count_seeds(rows: DataFrame, block: ItemBlock) -> None:
    """Number of documents with each seed of the block; sets the block's rare seeds."""
    sent = rows.sparkSession.sparkContext.broadcast(block)

    def run(batches):
        own = sent.value
        total = np.zeros(own.n_seeds, np.int64)
        for batch in small_batches(batches, "text"):
            for text in raw_texts(batch.column("text")):
                words = own.number(text)
                for n in own.lengths:
                    total[own.seeds[n][3][np.unique(own.hits(words, n)[1])]] += 1
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(total[at])], ["seed", "n"])

    counted = rows.select("text").mapInArrow(run, "seed int, n long").groupBy("seed").agg(F.sum("n").alias("n")).toArrow()
    documents = np.zeros(block.n_seeds, np.int64)
    documents[counted.column("seed").to_numpy()] = counted.column("n").to_numpy()
    sent.unpersist()
    block.keep_rare(documents)


def leaks(docs: DataFrame, items: DataFrame, s: AlignSettings = AlignSettings(), id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row for each document and item that align with at least `least_ratio`."""
    rows = id_and_text(docs, id_col, text_col)
    out = docs.sparkSession.createDataFrame([], FOUND)
    for block in item_blocks(items, s, item_col, item_text):
        count_seeds(rows, block)
        sent = docs.sparkSession.sparkContext.broadcast(block)

        def run(batches, sent=sent):
            own = sent.value
            for batch in small_batches(batches, "text"):
                found = [(d, *m) for d, t in zip(batch.column("doc_id").to_pylist(), raw_texts(batch.column("text"))) for m in own.matches(own.number(t))]
                if found:
                    kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int32(), pa.int32(), pa.int32(), pa.int32())
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*found), kinds)], ["doc_id", "item_id", "ratio", "matched", "item_words", "begin_word", "end_word"])

        out = out.unionAll(rows.mapInArrow(run, FOUND))
    return out


def without_leaks(docs: DataFrame, items: DataFrame, s: AlignSettings = AlignSettings(), text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The documents, with all their columns, that align with no item; nothing is shuffled."""
    rows = docs.select(F.coalesce(docs[text_col].cast("string"), F.lit("")).alias("text"))
    kept = docs
    for block in item_blocks(items, s, item_col, item_text):
        count_seeds(rows, block)
        sent = docs.sparkSession.sparkContext.broadcast(block)

        def run(batches, sent=sent):
            own = sent.value
            for batch in small_batches(batches, text_col):
                clean = [not any(True for _ in own.matches(own.number(t))) for t in raw_texts(batch.column(text_col))]
                yield batch.filter(pa.array(clean, pa.bool_()))

        kept = map_rows(kept, run, kept.schema)
    return kept
