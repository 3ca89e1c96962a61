"""Groups of texts linked by a Jaccard similarity of at least 0.8 of their sets of five-word shingles.

Two sources give candidate pairs, and every candidate is verified on the whole sets, unless sketches
of the sets (one bit for each of `SKETCH` classes of shingles) already show more shingles in one set
alone than similar sets can have.  First the
Gray-order index over 64-bit fingerprints of the same shingles: fingerprints within `NEAR` bits.  No
radius of practical use keeps all pairs (at 0.8 two fingerprints differ in about ten bits, often in
fifteen), so what it leaves open is closed by the sets themselves.  Under any one order of the
shingles, two sets with similarity 4/5 share a shingle among the first |x| - ceil(4/5 |x|) + 1 of
each.  The order puts shingles first that a sample of the documents holds seldom; it decides how
many candidates there are, never which links are found.

Texts with equal sets are one node.  Of the nodes of one shingle those that carry one label already
are not tried again; a node is tried with the first `FIRST` of its shingle's nodes, then with the
next ones in windows that widen `WIDER` times, until no shingle has nodes of two labels left to try:
near copies of one text need a number of tries in proportion to theirs, and no pair that could join
two groups is left out.

Cases: null and empty texts have the empty set and are linked to each other; a text of up to five
words is one shingle; a null key never names a component unless all its keys are null.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.llm.common import LOWER_TABLE, id_and_text, raw_texts, small_batches
from levelindex.llm.simhash_gray import components, fingerprint, links

WORDS = 5
COUNTERS = 1 << 20
SAMPLE = 8
PAIRS_AT_ONCE = 64
NEAR = 4
FIRST, WIDER = 8, 16
SKETCH = 2048
#: Nodes whose keys (24 bytes each) go to the workers; more meet the texts in a shuffled join.
BROADCAST_NODES = 1 << 20
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def shingles(text: bytes) -> np.ndarray:
    """Sorted distinct hashes of the runs of five words."""
    words = text.translate(LOWER_TABLE).split()
    if not words:
        return np.zeros(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(w) for w in words), np.uint64, len(words))
    n = min(WORDS, len(h))
    out = np.full(len(h) - n + 1, n, np.uint64)
    for i in range(n):
        out = (out ^ h[i : i + len(out)]) * MULTIPLIER
        out ^= out >> np.uint64(29)
    return np.unique(out)


def node_of(own: np.ndarray) -> int:
    return int(np.array(xxhash.xxh64_intdigest(own.tobytes()), np.uint64).view(np.int64)) if len(own) else 0


def similar(common: int, a: int, b: int) -> bool:
    """Whether common / (a + b - common) is at least 4/5, in whole numbers."""
    return 9 * common >= 4 * (a + b)


def sketch(own: np.ndarray) -> bytes:
    out = np.zeros(SKETCH, bool)
    out[(own >> np.uint64(40)) & np.uint64(SKETCH - 1)] = True
    return np.packbits(out).tobytes()


def prefix(own: np.ndarray, often: np.ndarray) -> np.ndarray:
    """The first shingles in the order, as many as a similar set can't avoid."""
    if not len(own):
        return own
    n = len(own) - -(-4 * len(own) // 5) + 1
    order = np.lexsort((own, often[own & np.uint64(COUNTERS - 1)]))
    return own[order[:n]]


def counts(rows: DataFrame) -> np.ndarray:
    """Counters of shingles over a sample of the documents, many shingles to one counter."""

    def run(batches):
        total = np.zeros(COUNTERS, np.int64)
        for batch in small_batches(batches, "text"):
            for text in raw_texts(batch.column("text")):
                total[np.unique(shingles(text) & np.uint64(COUNTERS - 1)).astype(np.int64)] += 1
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(total[at])], ["at", "n"])

    some = rows.where(F.pmod(F.xxhash64("text"), F.lit(SAMPLE)) == 0).select("text")
    found = some.mapInArrow(run, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).select("at", F.least("n", F.lit(1 << 30)).cast("int").alias("n")).toArrow()
    out = np.zeros(COUNTERS, np.int32)
    out[found.column("at").to_numpy()] = found.column("n").to_numpy()
    return out


def nodes_of(rows: DataFrame, often: np.ndarray) -> DataFrame:
    """doc_id, row (a hash of the text), node, its fingerprint, the size of its set, the set's first shingles and its sketch."""
    sent = rows.sparkSession.sparkContext.broadcast(often)
    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.list_(pa.int64()), pa.binary())

    def run(batches):
        own = sent.value
        for batch in small_batches(batches, "text"):
            texts = raw_texts(batch.column("text"))
            sets = [shingles(t) for t in texts]
            codes = np.array([fingerprint(t, WORDS) for t in texts], np.uint64).view(np.int64)
            found = ([node_of(x) for x in sets], codes, [len(x) for x in sets], [prefix(x, own).view(np.int64) for x in sets], [sketch(x) for x in sets])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("row"), *(pa.array(c, k) for c, k in zip(found, kinds))], ["doc_id", "row", "node", "fp", "size", "first", "bits"])

    return rows.mapInArrow(run, "doc_id long, row long, node long, fp long, size int, first array<long>, bits binary")


def whole_sets(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """node and its whole set as bytes, for the nodes in `wanted` (node, at: key and row of one text)."""

    def run(batches):
        for batch in small_batches(batches, "text"):
            found = [shingles(t).tobytes() for t in raw_texts(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("node"), pa.array(found, pa.binary())], ["node", "items"])

    at = wanted.select("node", F.col("at.doc_id").alias("__id"), F.col("at.row").alias("__row"))
    at = F.broadcast(at) if wanted.count() <= BROADCAST_NODES else at
    texts = rows.join(at, rows["doc_id"].eqNullSafe(at["__id"]) & (rows["row"] == at["__row"])).select("node", "text")
    return texts.mapInArrow(run, "node long, items binary").dropDuplicates(["node"])


def possible(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """The pairs whose sketches allow a similarity of 4/5: none has more bits alone than a similar set has shingles alone."""

    def run(batches):
        for batch in batches:
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(batch.num_rows, SKETCH // 8) for c in ("x", "y"))
            sa, sb = (batch.column(c).to_numpy().astype(np.int64) for c in ("sa", "sb"))
            least = -(-4 * (sa + sb) // 9)
            alone = lambda one, other: np.bitwise_count(one & ~other).sum(axis=1)
            yield batch.select(["a", "b"]).filter(pa.array((alone(x, y) <= sa - least) & (alone(y, x) <= sb - least)))

    a, b = (nodes.select(F.col("node").alias(n), F.col("size").alias(f"s{n}"), F.col("bits").alias(c)) for n, c in (("a", "x"), ("b", "y")))
    return pairs.join(a, "a").join(b, "b").mapInArrow(run, "a long, b long")


def verified(pairs: DataFrame, nodes: DataFrame, rows: DataFrame) -> DataFrame:
    """The pairs (a, b) that are similar; sets that many pairs ask for are dealt out in copies."""
    pairs = scratch.save(possible(pairs, nodes), "pairs")
    if pairs.isEmpty():
        return pairs
    wanted = scratch.save(nodes.join(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "node", "left_semi").select("node", "at"), "wanted")
    sets = scratch.save(whole_sets(rows, wanted), "sets")

    def run(batches):
        for batch in batches:
            ok = []
            for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist()):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                ok.append(similar(len(np.intersect1d(x, y, assume_unique=True)), len(x), len(y)))
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    hot = pairs.groupBy("a").agg(F.ceil(F.count("*") / PAIRS_AT_ONCE).cast("int").alias("copies")).where("copies > 1")
    hot = F.broadcast(scratch.save(hot, "hot"))
    asked = pairs.join(hot, "a", "left").select("a", "b", F.pmod(F.xxhash64("b"), F.coalesce("copies", F.lit(1))).cast("int").alias("copy"))
    left = sets.join(hot, sets["node"] == hot["a"], "left").select("node", "items", F.explode(F.sequence(F.lit(0), F.coalesce("copies", F.lit(1)) - 1)).alias("copy"))
    left = left.select(F.col("node").alias("a"), F.col("items").alias("x"), "copy")
    right = sets.select(F.col("node").alias("b"), F.col("items").alias("y"))
    return asked.join(right, "b").join(left, ["a", "copy"]).select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def fingerprint_pairs(nodes: DataFrame) -> DataFrame:
    """a, b: candidates by the Gray-order index. Nodes of one fingerprint with the least of them, and these along the index's links."""
    least = scratch.save(nodes.groupBy("fp").agg(F.min("node").alias("least")), "fingerprints")
    same = nodes.join(least, "fp").where("node != least").select(F.col("least").alias("a"), F.col("node").alias("b"))
    found = links(least.select("fp"), NEAR)
    apart = found.join(least.select(F.col("fp").alias("a"), F.col("least").alias("x")), "a").join(least.select(F.col("fp").alias("b"), F.col("least").alias("y")), "b")
    return same.unionAll(apart.select("x", "y"))


def similar_nodes(groups: DataFrame, near: DataFrame, nodes: DataFrame, rows: DataFrame) -> DataFrame | None:
    """node, root of the nodes that have a link; None without links. `near` gives the first candidates."""
    links, labels, low, pairs, open_ = None, None, 0, near, groups
    while True:
        new = scratch.save(verified(pairs, nodes, rows), "similar")
        if not new.isEmpty():
            links = new if links is None else links.unionAll(new)
            labels = scratch.save(components(links), "roots")
        open_ = open_.where(F.col("n") > low + 1).withColumn("root", F.col("node"))
        if labels is not None:  # a shingle whose nodes have one label stays so
            token = Window.partitionBy("token")
            open_ = open_.drop("root").join(labels, "node", "left").withColumn("root", F.coalesce("root", "node"))
            open_ = open_.withColumn("least", F.min("root").over(token)).withColumn("most", F.max("root").over(token)).where("least != most").drop("least", "most")
        open_ = scratch.save(open_, "open")
        if open_.isEmpty():
            return labels
        high = low + FIRST if low == 0 else WIDER * low
        a = open_.where((F.col("rank") >= low) & (F.col("rank") < high)).select("token", F.col("node").alias("a"), F.col("size").alias("sa"), F.col("place").alias("pa"), F.col("rank").alias("ra"), F.col("root").alias("la"))
        b = open_.where(F.col("rank") > low).select("token", F.col("node").alias("b"), F.col("size").alias("sb"), F.col("place").alias("pb"), F.col("rank").alias("rb"), F.col("root").alias("lb"))
        fits = F.expr("9 * least(sa - pa, sb - pb) >= 4 * (sa + sb)")  # what can still be shared from this shingle on
        pairs = a.join(b, "token").where((F.col("rb") > F.col("ra")) & (F.col("la") != F.col("lb")) & fits).select("a", "b").distinct()
        low = high


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, component_id (its smallest key), row (a hash of the text) and root of every row."""
    rows = id_and_text(docs, id_col, text_col).withColumn("row", F.xxhash64("text"))
    placed = scratch.save(nodes_of(rows, counts(rows)), "nodes")
    nodes = placed.groupBy("node").agg(F.first("size").alias("size"), F.first("first").alias("first"))
    token = Window.partitionBy("token")
    groups = nodes.select("node", "size", F.posexplode("first").alias("place", "token"))
    groups = groups.withColumn("n", F.count("*").over(token)).where("n > 1").withColumn("rank", F.row_number().over(token.orderBy("size", "node")) - 1)
    groups = scratch.save(groups, "groups")
    shared = groups.select("node").distinct()  # others can't be similar to any
    alone = placed.drop("first").join(shared, "node", "left_semi").groupBy("node")
    alone = scratch.save(alone.agg(F.min(F.struct("doc_id", "row")).alias("at"), F.min("fp").alias("fp"), F.first("size").alias("size"), F.first("bits").alias("bits")), "shared")
    labels = similar_nodes(groups, fingerprint_pairs(alone.select("node", "fp")), alone, rows)
    named = placed.groupBy("node").agg(F.min("doc_id").alias("least"))
    named = named.withColumn("root", F.col("node")) if labels is None else named.join(labels, "node", "left").withColumn("root", F.coalesce("root", "node"))
    named = scratch.save(named, "named")
    names = named.groupBy("root").agg(F.min("least").alias("component_id"))
    return placed.select("doc_id", "row", "node").join(named.select("node", "root"), "node").join(names, "root").select("doc_id", "component_id", "row", "root")
