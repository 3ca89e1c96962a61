"""SimHash near-duplicates through a hierarchical index over fingerprints in Gray order.

Distinct fingerprints are placed in several rotated orders, one for each band of bits: a band's
value is the top node of that order, and two fingerprints that differ in at most `distance` bits
agree in at least one of `distance + 1` bands.  Inside a top node the fingerprints are sorted by
Gray rank of the rotated bits, so neighbours share long runs of bits; leaves of `LEAF` and, level
upon level, nodes of `FANOUT` children keep the mask and pattern of the bits that all their members
share, up to at most `FANOUT` nodes.  A query block goes down, and a node falls away when the
differences inside its mask exceed the limit.  Bits that are shared higher up are not counted again
below: the sum so far is carried down.

A top node gives a spanning forest of its links, never all pairs.  Components come from repeated
minimum labels with pointer jumping over tables; nothing is gathered on the driver.

Cases: null and empty texts have fingerprint zero and link to each other like any other; a null key
never becomes a component's name unless all its keys are null; repeated rows are kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.llm.common import LOWER_TABLE, id_and_text, raw_texts, small_batches

LEAF, FANOUT, BITS = 32, 32, 64
QUERY_BLOCK = 2048
SHINGLES_AT_ONCE = 1 << 17


def fingerprint(text: bytes, n: int = 4) -> int:
    """Bits set in more than half of the hashes of all word shingles, repeats included."""
    words = text.translate(LOWER_TABLE).split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= n:
        return xxhash.xxh64_intdigest(joined, 42)
    ends = np.cumsum([len(w) + 1 for w in words])
    begins = np.concatenate(([0], ends[: -n]))
    last = ends[n - 1 :] - 1
    digest = xxhash.xxh64_intdigest
    ones, total = np.zeros(BITS, np.int64), len(words) - n + 1
    for at in range(0, total, SHINGLES_AT_ONCE):
        spans = zip(begins[at : at + SHINGLES_AT_ONCE].tolist(), last[at : at + SHINGLES_AT_ONCE].tolist())
        h = np.array([digest(joined[a:b], 42) for a, b in spans], ">u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > total).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, the fingerprint as a signed long, and a hash of the text that tells rows of one key apart."""

    def run(batches):
        for batch in small_batches(batches, "text"):
            found = np.array([fingerprint(t, shingle) for t in raw_texts(batch.column("text"))], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("row"), pa.array(found.view(np.int64))], ["doc_id", "row", "fp"])

    rows = id_and_text(docs, id_col, text_col)
    return rows.withColumn("row", F.xxhash64("text")).mapInArrow(run, "doc_id long, row long, fp long")


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Position of a code word in the reflected Gray sequence."""
    r = x.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        r ^= r >> np.uint64(shift)
    return r


def bands(distance: int) -> list[tuple[int, int]]:
    """First bit and width of the bands, from the top."""
    edges = [round(i * BITS / (distance + 1)) for i in range(distance + 2)]
    return [(a, b - a) for a, b in zip(edges, edges[1:])]


def shared_bits(ones: np.ndarray, zeros: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Bits that are one, and bits that are zero, in all of each run of `size` members."""
    at = np.arange(0, len(ones), size)
    return np.bitwise_and.reduceat(ones, at), np.bitwise_and.reduceat(zeros, at)


class GrayIndex:
    """A tree of shared bits over fingerprints in Gray order."""

    def __init__(self, fps: np.ndarray, first_bit: int = 0):
        turned = fps << np.uint64(first_bit) | (fps >> np.uint64(BITS - first_bit) if first_bit else np.uint64(0))
        self.order = np.argsort(gray_rank(turned), kind="stable")
        self.fp = fps[self.order]
        levels = [shared_bits(self.fp, ~self.fp, LEAF)]
        while len(levels[-1][0]) > FANOUT:
            levels.append(shared_bits(*levels[-1], FANOUT))
        #: From the top: patterns, and masks without the bits that the node above has told already.
        self.levels, above = [], None
        for ones, zeros in reversed(levels):
            mask = ones | zeros
            own = mask if above is None else mask & ~above[np.arange(len(mask)) // FANOUT]
            self.levels.append((ones, own))
            above = mask

    def near(self, queries: np.ndarray, limit: int, after: int):
        """Pairs (query, member) with at most `limit` differing bits; members before `after` are left out."""
        count = np.bitwise_count
        size = LEAF * FANOUT ** (len(self.levels) - 1)
        n = len(self.levels[0][0])
        q, node, sofar = np.repeat(np.arange(len(queries)), n), np.tile(np.arange(n), len(queries)), np.zeros(len(queries) * n, np.uint8)
        for depth, (bits, mask) in enumerate(self.levels):
            if depth:
                node = (node[:, None] * FANOUT + np.arange(FANOUT)).ravel()
                q, sofar = np.repeat(q, FANOUT), np.repeat(sofar, FANOUT)
                size //= FANOUT
            fits = (node < len(bits)) & ((node + 1) * size > after)
            q, node, sofar = q[fits], node[fits], sofar[fits]
            sofar = sofar + count((queries[q] ^ bits[node]) & mask[node])
            fits = sofar <= limit
            q, node, sofar = q[fits], node[fits], sofar[fits]
        out_q, out_m = [q[:0]], [q[:0]]
        for at in range(0, len(q), 1 << 16):
            member = (node[at : at + (1 << 16), None] * LEAF + np.arange(LEAF)).ravel()
            whose = np.repeat(q[at : at + (1 << 16)], LEAF)
            ok = (member < len(self.fp)) & (member >= after)
            member, whose = member[ok], whose[ok]
            ok = count(queries[whose] ^ self.fp[member]) <= limit
            out_q.append(whose[ok])
            out_m.append(member[ok])
        return np.concatenate(out_q), np.concatenate(out_m)


def forest(fps: np.ndarray, limit: int, first_bit: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that join the same fingerprints as all links within the limit do."""
    n = len(fps)
    if n < 2:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    if n == 2:
        near = int(np.bitwise_count(fps[0] ^ fps[1])) <= limit
        return (fps[:1], fps[1:]) if near else (fps[:0], fps[:0])
    index = GrayIndex(fps, first_bit)
    label = np.arange(n)
    for at in range(0, n, QUERY_BLOCK):
        q, m = index.near(index.fp[at : at + QUERY_BLOCK], limit, at)
        q = q + at
        real = q != m
        q, m = q[real], m[real]
        while len(q):  # hooking and shortcutting until each pair has one label
            a, b = label[q], label[m]
            apart = a != b
            if not apart.any():
                break
            q, m, a, b = q[apart], m[apart], a[apart], b[apart]
            np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
            while (label[label] != label).any():
                label = label[label]
    order = np.argsort(label, kind="stable")
    same = label[order][1:] == label[order][:-1]
    return index.fp[order[:-1][same]], index.fp[order[1:][same]]


def links(distinct: DataFrame, distance: int, rows_at_once: int = 50_000) -> DataFrame:
    """a, b: a spanning forest of the links in every top node, over all bands."""
    split = bands(distance)
    signed = F.col("fp")
    keys = [F.struct(F.lit(i).alias("band"), F.shiftrightunsigned(F.shiftleft(signed, first), BITS - width).alias("value")) for i, (first, width) in enumerate(split)]
    lots = max(1, len(split) * distinct.count() // rows_at_once)  # each lot holds whole top nodes
    placed = distinct.select("fp", F.explode(F.array(*keys)).alias("key")).select("fp", F.col("key.band").alias("band"), F.col("key.value").alias("value"))
    placed = placed.withColumn("lot", F.pmod(F.xxhash64("band", "value"), F.lit(lots)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(batches)
        fps, band, value = (rows.column(c).to_numpy() for c in ("fp", "band", "value"))
        order = np.lexsort((value, band))
        fps, band, value = fps[order].view(np.uint64), band[order], value[order]
        edges = np.flatnonzero((band[1:] != band[:-1]) | (value[1:] != value[:-1])) + 1
        for at, to in zip([0, *edges], [*edges, len(fps)]):
            a, b = forest(fps[at:to], distance, split[band[at]][0])
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    return placed.groupBy("lot").applyInArrow(run, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """node, root for every node that has a link: least labels of neighbours, then labels of labels."""
    spark = edges.sparkSession
    both = scratch.save(edges.select("a", "b").union(edges.select("b", "a")).distinct(), "links")
    labels = scratch.save(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("root")), "labels")
    while True:
        around = both.join(labels.select(F.col("node").alias("b"), F.col("root").alias("r")), "b").groupBy(F.col("a").alias("node")).agg(F.min("r").alias("r"))
        less = labels.join(around, "node").select("node", F.least("root", "r").alias("root"), F.col("root").alias("old"))
        less = scratch.save(less, "less")
        jump = less.select(F.col("node").alias("root"), F.col("root").alias("further"))
        new = scratch.save(less.join(jump, "root").select("node", F.col("further").alias("root"), "old"), "labels")
        if new.where("root != old").isEmpty():
            return new.select("node", "root")
        labels = new.select("node", "root")


def near_duplicates(docs: DataFrame, distance: int = 4, shingle: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint, component_id, row (a hash of the text) and root (tells components apart, should two share a key) of every row."""
    rows = scratch.save(fingerprints(docs, shingle, id_col, text_col), "fingerprints")
    distinct = rows.groupBy("fp").agg(F.min("doc_id").alias("least"))
    distinct = scratch.save(distinct, "distinct")
    roots = components(links(distinct.select("fp"), distance))
    placed = distinct.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    placed = scratch.save(placed, "placed")
    names = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    named = placed.join(names, "root").select("fp", "component_id", "root")
    named = scratch.save(named, "named")
    text = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return rows.join(named, "fp").select("doc_id", text.alias("fingerprint"), "component_id", "row", "root")
