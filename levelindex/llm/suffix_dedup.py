"""Removal of long repeated byte strings across documents, by suffix sorting.

A byte goes if a string of `least` bytes that covers it also starts in a document with a smaller
key.  Suffixes can't all be moved at 100 TB, so they are first parted so that equal ones meet:

1. Documents form blocks by a hash of their key.  In every window of `least` bytes the 20-gram with
   the smallest hash is the window's anchor, so equal windows have equal anchors.  A block sends each
   anchor once.
2. Anchors that occur in more than one document go back to their blocks; all other windows are
   unique and done with.
3. A block sends the context of each shared anchor (all its windows together, at most
   2 * least - 20 bytes), equal contexts once with the smallest key.  Contexts are dealt by anchor.
4. Contexts of one anchor that differ are suffix-sorted, a bucket at a time, with difference-cover
   ranks for ties; equal windows stand together and get the smallest key of their run.
5. Blocks learn the smallest key of each window and cut.

A hot passage is sent once a block, not once a document.  Cases: null text is empty; a document
without a key neither removes nor loses anything; documents that share a key don't remove from each
other; texts shorter than `least` stay; repeats inside one document stay.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.llm.common import tidy
from levelindex.llm.suffix_blocks import suffix_order

GRAM = 20
BLOCK_BYTES = 3 << 20
PART_BYTES = 8 << 20
PIECE = 4 << 20
RESULT = "doc_id long, row long, n_bytes long, n_removed long, begins array<long>, ends array<long>, kept binary"


def gram_hashes(raw: np.ndarray) -> np.ndarray:
    """A mixed 64-bit hash of every 20-gram."""
    h = raw.astype(np.uint64) + np.uint64(1)
    step, size = np.uint64(0x9E3779B97F4A7C15), 1
    power = step
    quad = None
    while size < 16:
        h = h[:-size] * power + h[size:]
        power, size = power * power, size * 2
        if size == 4:
            quad, quad_power = h, power
    h = h[: len(h) - 4] * quad_power + quad[16 : 16 + len(h) - 4]
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    return h


def window_minimum(x: np.ndarray, w: int) -> np.ndarray:
    size = 1
    while size * 2 <= w:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    return np.minimum(x[: len(x) - (w - size)], x[w - size :]) if w > size else x


class Runs:
    """Windows of some documents by anchor: document, first window, number of windows, anchor's hash and offset."""

    def __init__(self, texts: list[bytes], least: int):
        found = []
        with np.errstate(over="ignore"):
            group, begins, held = [], [], 0
            for i, t in enumerate([*texts, None]):
                if group and (t is None or held + len(t) > PIECE):
                    found.append(self.scan(b"".join(texts[j] for j in group), group, begins, [len(texts[j]) for j in group], least))
                    group, begins, held = [], [], 0
                if t is None:
                    continue
                if len(t) > PIECE:
                    for at in range(0, max(len(t) - least + 1, 1), PIECE):  # windows of a long text, each once
                        part = t[at : at + PIECE + least - 1]
                        one = self.scan(part, [i], [0], [len(part)], least)
                        found.append((one[0], one[1] + at, *one[2:]))
                    continue
                group.append(i)
                begins.append(held)
                held += len(t)
        self.doc, self.start, self.count, self.anchor, self.offset = (np.concatenate([f[k] for f in found]) if found else np.zeros(0, np.int64) for k in range(5))

    @staticmethod
    def scan(raw: bytes, docs: list[int], begins: list[int], sizes: list[int], least: int):
        data = np.frombuffer(raw, np.uint8)
        if len(data) < least:
            return tuple(np.zeros(0, np.uint64 if k == 3 else np.int64) for k in range(5))
        h = gram_hashes(data)
        w = least - GRAM + 1
        packed = (h & ~np.uint64(0xFFFFFF)) | np.arange(len(h), dtype=np.uint64)
        at = (window_minimum(packed, w) & np.uint64(0xFFFFFF)).astype(np.int64)
        sizes, begins = np.array(sizes), np.array(begins)
        room = np.maximum(sizes - least + 1, 0)
        windows = np.repeat(begins - (np.cumsum(room) - room), room) + np.arange(room.sum())
        owner = np.repeat(np.arange(len(docs)), room)
        anchor = at[windows]
        if not len(windows):
            return tuple(np.zeros(0, np.uint64 if k == 3 else np.int64) for k in range(5))
        new = np.flatnonzero(np.concatenate(([True], (anchor[1:] != anchor[:-1]) | (owner[1:] != owner[:-1]))))
        first = windows[new]
        return np.array(docs)[owner[new]], first - begins[owner[new]], np.diff(np.append(new, len(windows))), h[anchor[new]], anchor[new] - first


def in_sorted(values: np.ndarray, table: np.ndarray) -> np.ndarray:
    if not len(table):
        return np.zeros(len(values), bool)
    at = np.minimum(np.searchsorted(table, values), len(table) - 1)
    return table[at] == values


def block_rows(table: pa.Table) -> tuple[list[int | None], list[int], list[bytes]]:
    """Keys, row numbers and texts of a block, in an order that does not depend on arrival."""
    keys, rows = table.column("doc_id").to_pylist(), table.column("row").to_pylist()
    texts = [x or b"" for x in pc.cast(table.column("text"), pa.binary()).to_pylist()]
    order = sorted(range(len(keys)), key=lambda i: (keys[i] is None, keys[i] or 0, texts[i], rows[i]))
    return [keys[i] for i in order], [rows[i] for i in order], [texts[i] for i in order]


def with_key(keys: list, texts: list[bytes]) -> tuple[np.ndarray, list[bytes]]:
    """Keys as numbers, and texts with those of keyless documents emptied."""
    return np.array([k if k is not None else 0 for k in keys], np.int64), [t if k is not None else b"" for k, t in zip(keys, texts)]


def parted(anchor: np.ndarray, parts: int) -> np.ndarray:
    return ((anchor >> np.uint64(33)) % np.uint64(parts)).astype(np.int32)


def block_anchors(table: pa.Table, block: int, parts: int, least: int):
    keys, _, texts = block_rows(table)
    numbers, texts = with_key(keys, texts)
    runs = Runs(texts, least)
    order = np.lexsort((numbers[runs.doc], runs.anchor)) if len(runs.doc) else np.zeros(0, int)
    anchor, key = runs.anchor[order], numbers[runs.doc][order]
    if not len(anchor):
        return
    new = np.flatnonzero(np.concatenate(([True], anchor[1:] != anchor[:-1])))
    last = np.append(new[1:], len(anchor)) - 1
    several = key[new] != key[last]
    anchor = anchor[new]
    part = parted(anchor, parts)
    for p in np.unique(part):
        mine = part == p
        yield int(p), block, anchor[mine].tobytes(), np.packbits(several[mine]).tobytes()


def distinct_contexts(runs: Runs, keep: np.ndarray, texts: list[bytes], least: int):
    """Occurrences of kept runs, numbered by equal context; and the contexts with one occurrence each."""
    occurrences = np.flatnonzero(keep)
    numbers: dict[tuple[int, bytes], int] = {}
    ids = np.empty(len(occurrences), np.int64)
    doc, start, end, offset = runs.doc[occurrences].tolist(), runs.start[occurrences].tolist(), (runs.start + runs.count + least - 1)[occurrences].tolist(), runs.offset[occurrences].tolist()
    for i, (d, a, b, o) in enumerate(zip(doc, start, end, offset)):
        key = (o, texts[d][a:b])
        n = numbers.get(key)
        if n is None:
            n = numbers[key] = len(numbers)
        ids[i] = n
    return occurrences, ids, list(numbers)


def block_contexts(docs: pa.Table, shared: pa.Table, block: int, parts: int, least: int):
    if not docs.num_rows or not shared.num_rows:
        return
    table = np.sort(np.concatenate([np.frombuffer(b, np.uint64) for b in shared.column("data").to_pylist()]))
    keys, _, texts = block_rows(docs)
    numbers, texts = with_key(keys, texts)
    runs = Runs(texts, least)
    occurrences, ids, contexts = distinct_contexts(runs, in_sorted(runs.anchor, table), texts, least)
    if not contexts:
        return
    order = np.argsort(ids, kind="stable")
    at = np.searchsorted(ids[order], np.arange(len(contexts)))
    key = numbers[runs.doc[occurrences]][order]
    low, high = np.minimum.reduceat(key, at), np.maximum.reduceat(key, at)
    part = parted(runs.anchor[occurrences][order][at], parts)
    for p in np.unique(part):
        mine = np.flatnonzero(part == p)
        yield int(p), block, mine.astype(np.int32).tobytes(), np.array([contexts[i][0] for i in mine], np.uint8).tobytes(), np.array([len(contexts[i][1]) for i in mine], np.uint8).tobytes(), low[mine].tobytes(), high[mine].tobytes(), b"".join(contexts[i][1] for i in mine)


def least_keys(rows: list[dict], least: int):
    """For each block the runs (context, first window, windows, smallest key) where a smaller key has the window."""
    known: dict[tuple[int, bytes], int] = {}
    smallest: list[int] = []
    told = []  # block, numbers of contexts in the block, our numbers, largest keys
    for r in rows:
        offsets, sizes, low = np.frombuffer(r["offsets"], np.uint8).tolist(), np.frombuffer(r["sizes"], np.uint8).tolist(), np.frombuffer(r["low"], np.int64).tolist()
        ours, at, text = [], 0, r["text"]
        for o, n, k in zip(offsets, sizes, low):
            key = (o, text[at : at + n])
            at += n
            i = known.get(key)
            if i is None:
                i = known[key] = len(smallest)
                smallest.append(k)
            elif k < smallest[i]:
                smallest[i] = k
            ours.append(i)
        told.append((r["block"], np.frombuffer(r["ids"], np.int32), np.array(ours), np.frombuffer(r["high"], np.int64)))
    contexts = list(known)
    by_anchor: dict[bytes, list[int]] = {}
    for i, (o, c) in enumerate(contexts):
        by_anchor.setdefault(c[o : o + GRAM], []).append(i)
    several = [i for group in by_anchor.values() if len(group) > 1 for i in group]
    # context, first window, windows, key: contexts alone with their anchor have one key for all windows
    low = np.array(smallest, np.int64)
    size = np.array([len(c) for _, c in contexts], np.int64) - least + 1
    alone = np.ones(len(contexts), bool)
    alone[several] = False
    alone = np.flatnonzero(alone)
    found = [(alone, np.zeros(len(alone), np.int64), size[alone], low[alone])]
    if several:
        found.append(sorted_windows([contexts[i][1] for i in several], np.array(several), low, least))
    ctx, first, count, key = (np.concatenate([f[k] for f in found]) for k in range(4))
    order = np.argsort(ctx, kind="stable")
    ctx, first, count, key = ctx[order], first[order], count[order], key[order]
    begins = np.searchsorted(ctx, np.arange(len(contexts) + 1))
    for block, ids, ours, high in told:
        per = begins[ours + 1] - begins[ours]
        at = np.repeat(begins[ours] - (np.cumsum(per) - per), per) + np.arange(per.sum())
        useful = key[at] < np.repeat(high, per)
        if useful.any():
            at = at[useful]
            yield block, np.repeat(ids, per)[useful].astype(np.int32).tobytes(), first[at].astype(np.uint8).tobytes(), count[at].astype(np.uint8).tobytes(), key[at].tobytes()


def sorted_windows(texts: list[bytes], names: np.ndarray, low: np.ndarray, least: int):
    """Smallest keys of windows of contexts that share an anchor, by suffix order."""
    sizes = np.array([len(t) for t in texts])
    begin = np.cumsum(sizes + 1) - (sizes + 1)
    text = np.zeros(int((sizes + 1).sum()), np.int64)
    inside = np.ones(len(text), bool)
    inside[begin + sizes] = False
    text[inside] = np.frombuffer(b"".join(texts), np.uint8).astype(np.int64) + 1
    windows = sizes - least + 1
    owner = np.repeat(np.arange(len(texts)), windows)
    starts = np.repeat(begin - (np.cumsum(windows) - windows), windows) + np.arange(windows.sum())
    owner_at = np.zeros(len(text), np.int64)
    owner_at[starts] = owner
    best = np.zeros(len(text), np.int64)
    held: tuple[np.ndarray, int] | None = None
    ordered = np.concatenate(list(suffix_order(text, starts, depth=least)))
    rows = np.arange(least)
    new = np.ones(len(ordered), bool)
    for at in range(1, len(ordered), 1 << 16):
        a, b = ordered[at - 1 : at - 1 + (1 << 16)], ordered[at : at + (1 << 16)]
        a = a[: len(b)]
        new[at : at + len(b)] = (text[a[:, None] + rows] != text[b[:, None] + rows]).any(axis=1)
    groups = np.flatnonzero(new)
    lowest = np.minimum.reduceat(low[names[owner_at[ordered]]], groups)
    best[ordered] = np.repeat(lowest, np.diff(np.append(groups, len(ordered))))
    value = best[starts]
    change = np.flatnonzero(np.concatenate(([True], (owner[1:] != owner[:-1]) | (value[1:] != value[:-1]))))
    return names[owner[change]], starts[change] - begin[owner[change]], np.diff(np.append(change, len(starts))), value[change]


def cut_block(docs: pa.Table, right: pa.Table, least: int, with_kept: bool):
    """Rows of the result for one block."""
    keys, rows, texts = block_rows(docs)
    numbers, searched = with_key(keys, texts)
    kinds = right.column("kind").to_pylist() if right.num_rows else []
    shared = [np.frombuffer(d, np.uint64) for d, k in zip(right.column("data").to_pylist(), kinds) if k == 0]
    cuts: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    if 1 in kinds:
        runs = Runs(searched, least)
        occurrences, ids, _ = distinct_contexts(runs, in_sorted(runs.anchor, np.sort(np.concatenate(shared))), searched, least)
        pick = [i for i, k in enumerate(kinds) if k == 1]
        take = lambda c, kind: np.concatenate([np.frombuffer(right.column(c)[i].as_py(), kind) for i in pick])
        ctx, first, count, key = take("data", np.int32), take("first", np.uint8).astype(np.int64), take("windows", np.uint8).astype(np.int64), take("key", np.int64)
        order = np.argsort(ctx, kind="stable")
        ctx, first, count, key = ctx[order], first[order], count[order], key[order]
        a, b = np.searchsorted(ctx, ids), np.searchsorted(ctx, ids, side="right")
        per = b - a
        at = np.repeat(a - (np.cumsum(per) - per), per) + np.arange(per.sum())
        doc = np.repeat(runs.doc[occurrences], per)
        begin = np.repeat(runs.start[occurrences], per) + first[at]
        end = begin + count[at] - 1 + least
        removed = key[at] < numbers[doc]
        doc, begin, end = doc[removed], begin[removed], end[removed]
        order = np.lexsort((begin, doc))
        doc, begin, end = doc[order], begin[order], end[order]
        edges = np.flatnonzero(np.concatenate(([True], doc[1:] != doc[:-1]))) if len(doc) else []
        for x, y in zip(edges, np.append(edges[1:], len(doc)).astype(int) if len(doc) else []):
            reach = np.maximum.accumulate(end[x:y])
            fresh = np.concatenate(([True], begin[x + 1 : y] > reach[:-1]))
            at = np.flatnonzero(fresh)
            cuts[int(doc[x])] = (begin[x:y][at], reach[np.append(at[1:], y - x) - 1])
    for i, (key, row, text) in enumerate(zip(keys, rows, texts)):
        begin, end = cuts.get(i, (np.zeros(0, np.int64), np.zeros(0, np.int64)))
        yield key, row, len(text), int((end - begin).sum()), begin.tolist(), end.tolist(), kept_bytes(text, begin, end) if with_kept else hashlib.sha256(kept_bytes(text, begin, end)).hexdigest().encode()


def kept_bytes(text: bytes, begin: np.ndarray, end: np.ndarray) -> bytes:
    return text if not len(begin) else b"".join(text[a:b] for a, b in zip([0, *end.tolist()], [*begin.tolist(), len(text)]))


def to_table(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    columns = list(zip(*rows)) if rows else [[] for _ in schema]
    tidy()
    return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)


ANCHORS = pa.schema([("part", pa.int32()), ("block", pa.int32()), ("anchors", pa.binary()), ("several", pa.binary())])
CONTEXTS = pa.schema([("part", pa.int32()), ("block", pa.int32()), ("ids", pa.binary()), ("offsets", pa.binary()), ("sizes", pa.binary()), ("low", pa.binary()), ("high", pa.binary()), ("text", pa.binary())])
REPLY = pa.schema([("block", pa.int32()), ("kind", pa.int32()), ("data", pa.binary()), ("first", pa.binary()), ("windows", pa.binary()), ("key", pa.binary())])
CUT = pa.schema([("doc_id", pa.int64()), ("row", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("begins", pa.list_(pa.int64())), ("ends", pa.list_(pa.int64())), ("kept", pa.binary())])


def ddl(schema: pa.Schema) -> str:
    names = {pa.int32(): "int", pa.int64(): "long", pa.binary(): "binary", pa.list_(pa.int64()): "array<long>"}
    return ", ".join(f"{f.name} {names[f.type]}" for f in schema)


def cut_repeats(rows: DataFrame, least: int = 50, with_kept: bool = True) -> DataFrame:
    """Spans to remove from rows of doc_id, row (any number that tells rows apart) and text.

    `kept` is what is left, or its sha256 in hexadecimal without `with_kept`.
    """
    if not GRAM < least <= 2 * GRAM + 80:
        raise ValueError("the length must be over 20 and at most 120 bytes")
    total = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks, parts = max(1, -(-total // BLOCK_BYTES)), max(12, -(-total // PART_BYTES))
    docs = rows.select("doc_id", "row", "text", F.pmod(F.hash(F.coalesce("doc_id", F.col("row"))), F.lit(blocks)).cast("int").alias("block"))

    def anchors(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        return to_table(list(block_anchors(table, key[0].as_py(), parts, least)), ANCHORS)

    def share(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        own = [np.frombuffer(b, np.uint64) for b in table.column("anchors").to_pylist()]
        several = [np.unpackbits(np.frombuffer(s, np.uint8), count=len(a)).astype(bool) for s, a in zip(table.column("several").to_pylist(), own)]
        values, counts = np.unique(np.concatenate(own), return_counts=True)
        common = np.union1d(values[counts > 1], np.concatenate([a[s] for a, s in zip(own, several)]))
        out = [(b, 0, a[hit].tobytes(), None, None, None) for b, a in zip(table.column("block").to_pylist(), own) if (hit := in_sorted(a, common)).any()]
        return to_table(out, REPLY)

    def contexts(key, left, right):
        return to_table(list(block_contexts(left, right, key[0].as_py(), parts, least)), CONTEXTS)

    def resolve(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        return to_table([(b, 1, *x) for b, *x in least_keys(table.to_pylist(), least)], REPLY)

    def cut(key, left, right):
        return to_table(list(cut_block(left, right, least, with_kept)) if left.num_rows else [], CUT)

    by_block = docs.groupBy("block")
    shared = scratch.save(by_block.applyInArrow(anchors, ddl(ANCHORS)).groupBy("part").applyInArrow(share, ddl(REPLY)), "anchors")
    sent = by_block.cogroup(shared.groupBy("block")).applyInArrow(contexts, ddl(CONTEXTS))
    answers = sent.groupBy("part").applyInArrow(resolve, ddl(REPLY))
    return by_block.cogroup(shared.unionByName(answers).groupBy("block")).applyInArrow(cut, ddl(CUT))


def repeated_bytes(docs: DataFrame, least: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every row."""
    text = F.coalesce(docs[text_col].cast("string"), F.lit(""))
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), text.alias("text")).withColumn("row", F.xxhash64("text"))
    return cut_repeats(rows, least, with_kept=False).select("doc_id", "n_bytes", "n_removed", F.size("begins").cast("long").alias("n_spans"), F.col("kept").cast("string").alias("kept_sha256"))
