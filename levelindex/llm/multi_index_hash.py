"""Nearest neighbours by multi-index hashing of learned rotated binary codes.

A rotation is learned on a bounded sample so that the signs of the rotated, centred vectors lose
little (alternating signs and an orthogonal fit).  Each code is split into substrings and every
substring is indexed.  If two codes differ in at most r bits, then of m substrings one differs in at
most r // m bits, and of the first r % m + 1 substrings one does or a later one in r // m - 1: probing
these neighbourhoods finds every code within r.  Candidates within r are ranked by their original
vectors in double precision.

The radius comes from `calibration` queries whose exact neighbours over all rows are known: it is the
one that holds `target` of them.  A query that finds fewer than k rows widens its radius until it
has k or has seen all, so nothing is capped.  Queries go to the workers in blocks of `query_block`
rows (a fixed number, hence a fixed size), rows are indexed in blocks of `index_block`.

Cases: null vectors, null or non-finite components, zero vectors and other dimensions than the most
frequent one take no part; null ids too; rows with one id are separate candidates, and none of them
is a candidate of that id's query; empty tables give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


LARGEST = float(np.finfo(float).max)
#: Codes see components within this bound, so that no product overflows; scores use the vectors as they are.
CODED = 1e100


@dataclass(frozen=True)
class HashSettings:
    bits: int = 64
    substrings: int = 4
    sample: int = 8192
    rounds: int = 30
    calibration: int = 96
    target: float = 0.97
    query_block: int = 8192
    index_block: int = 65_536
    seed: int = 13


def usable(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """vec_id and the vector as doubles, of rows that take part."""
    v = F.col("vec")
    rows = vectors.select(vectors[id_col].cast("long").alias("vec_id"), vectors[vec_col].cast("array<double>").alias("vec"))
    # the bound on the magnitude, the largest double, is false for null, nan and infinite components
    return rows.where(F.col("vec_id").isNotNull() & v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: F.coalesce(F.abs(x) <= F.lit(LARGEST), F.lit(False))) & F.exists(v, lambda x: x != 0))


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    flat = column.flatten() if not isinstance(column, pa.ChunkedArray) else column.combine_chunks().flatten()
    return flat.to_numpy(zero_copy_only=False).reshape(-1, dim)


class Codes:
    """Centre and rotation; codes are packed into 64-bit numbers."""

    def __init__(self, centre: np.ndarray, turn: np.ndarray):
        self.centre, self.turn = centre, turn

    @classmethod
    def learn(cls, sample: np.ndarray, s: HashSettings) -> "Codes":
        dim = sample.shape[1]
        sample = np.clip(sample, -CODED, CODED)
        centre = sample.mean(axis=0)
        x = sample - centre
        draw = np.random.default_rng(s.seed)
        parts, left = [], s.bits
        _, vectors = np.linalg.eigh(x.T @ x)
        while left > 0:
            n = min(left, dim)
            base = vectors[:, ::-1][:, :n]
            turn = np.linalg.qr(draw.normal(size=(n, n)))[0]
            low = x @ base
            for _ in range(s.rounds):
                u, _, vt = np.linalg.svd(low.T @ np.sign(low @ turn))
                turn = u @ vt
            parts.append(base @ turn)
            left -= n
        return cls(centre, np.concatenate(parts, axis=1))

    def pack(self, x: np.ndarray) -> np.ndarray:
        signs = (np.clip(x, -CODED, CODED) - self.centre) @ self.turn > 0
        return np.packbits(signs, axis=1).view(">u8").astype(np.uint64).ravel()


def masks_by_weight(width: int) -> list[np.ndarray]:
    """All substring differences, by number of bits."""
    return [np.array([sum(1 << b for b in c) for c in combinations(range(width), k)], np.int64) for k in range(width + 1)]


class MultiIndex:
    """Substring tables over one block of codes."""

    def __init__(self, codes: np.ndarray, s: HashSettings):
        self.codes, self.m, self.width = codes, s.substrings, s.bits // s.substrings
        self.masks = masks_by_weight(self.width)
        self.tables = []
        for i in range(self.m):
            sub = self.part(codes, i)
            order = np.argsort(sub, kind="stable")
            counts = np.bincount(sub, minlength=1 << self.width)
            self.tables.append((order, np.concatenate(([0], np.cumsum(counts)))))

    def part(self, codes: np.ndarray, i: int) -> np.ndarray:
        return ((codes >> np.uint64(i * self.width)) & np.uint64((1 << self.width) - 1)).astype(np.int64)

    def within(self, code: np.uint64, radius: int) -> np.ndarray:
        """Every row whose code differs in at most `radius` bits."""
        whole, extra = divmod(radius, self.m)
        hit = np.zeros(len(self.codes), bool)
        for i in range(self.m):
            reach = whole if i <= extra else whole - 1
            if reach < 0:
                continue
            order, starts = self.tables[i]
            mine = int(self.part(np.array([code], np.uint64), i)[0])
            probe = mine ^ np.concatenate(self.masks[: min(reach, self.width) + 1])
            begin, count = starts[probe], starts[probe + 1] - starts[probe]
            full = count > 0
            begin, count = begin[full], count[full]
            if len(begin):
                at = np.repeat(begin - (np.cumsum(count) - count), count) + np.arange(count.sum())
                hit[order[at]] = True
        rows = np.flatnonzero(hit)
        return rows[np.bitwise_count(self.codes[rows] ^ code) <= radius]


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k largest scores, ties to the smaller id."""
    if len(scores) > 4 * k:
        edge = np.partition(scores, len(scores) - k)[len(scores) - k]
        some = np.flatnonzero(scores >= edge)
        return some[np.lexsort((ids[some], -scores[some]))[:k]]
    return np.lexsort((ids, -scores))[:k]


FOUND = "query_id long, vec_id long, score double, distance int"


def probe(rows: DataFrame, queries: tuple[np.ndarray, np.ndarray], codes: Codes, radius: int | None, k: int, dim: int, s: HashSettings) -> DataFrame:
    """Per task the k best candidates of each query; radius None takes all rows (exact)."""
    sent = rows.sparkSession.sparkContext.broadcast((*queries, codes.centre, codes.turn))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q, centre, turn = sent.value
        code = Codes(centre, turn)
        qcode = code.pack(q)
        kept: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}

        def block(ids: np.ndarray, x: np.ndarray) -> None:
            own = code.pack(x)
            index = None if radius is None else MultiIndex(own, s)
            for i in range(len(qid)):
                r = radius
                while True:
                    near = np.arange(len(ids)) if index is None else index.within(qcode[i], r)
                    near = near[ids[near] != qid[i]]
                    if index is None or len(near) >= k or r >= s.bits:
                        break
                    r = min(s.bits, r + s.substrings)
                with np.errstate(over="ignore", invalid="ignore"):
                    score = x[near] @ q[i]
                got = (score, ids[near], np.bitwise_count(own[near] ^ qcode[i]).astype(np.int32))
                if i in kept:
                    got = tuple(np.concatenate(z) for z in zip(kept[i], got))
                top = best(got[0], got[1], k)
                kept[i] = tuple(z[top] for z in got)

        ids, vecs, held = [], [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            ids.append(batch.column("vec_id").to_numpy())
            vecs.append(matrix(batch.column("vec"), dim))
            held += batch.num_rows
            if held >= s.index_block:
                block(np.concatenate(ids), np.concatenate(vecs))
                ids, vecs, held = [], [], 0
        if held:
            block(np.concatenate(ids), np.concatenate(vecs))
        for i, (score, near, apart) in kept.items():
            if len(near):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(near), qid[i])), pa.array(near), pa.array(score), pa.array(apart)], ["query_id", "vec_id", "score", "distance"])

    return rows.mapInArrow(run, FOUND)


def top_k(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def nearest(vectors: DataFrame, k: int = 20, every: int = 20, s: HashSettings = HashSettings(), exact: bool = False, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score for each row whose id is divisible by `every`, against all rows."""
    spark = vectors.sparkSession
    rows = usable(vectors, id_col, vec_col)
    sizes = rows.groupBy(F.size("vec").alias("dim")).count().orderBy(F.desc("count"), "dim").first()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    if sizes is None:
        return empty
    dim = sizes["dim"]
    rows = rows.where(F.size("vec") == dim)
    by_hash = F.xxhash64("vec_id", F.lit(s.seed))
    few = lambda df, n: df.join(F.broadcast(df.select("vec_id").orderBy(by_hash, "vec_id").limit(n)), "vec_id", "left_semi").orderBy("vec_id").limit(n)
    sample = few(rows, s.sample).select("vec").toArrow()
    codes = Codes.learn(matrix(sample.column("vec"), dim), s)
    asked = rows.where(F.col("vec_id") % every == 0)
    some = few(asked, s.calibration).toArrow()
    if not some.num_rows:
        return empty
    take = lambda t: (t.column("vec_id").to_numpy(), matrix(t.column("vec"), dim))
    truth = top_k(probe(rows, take(some), codes, None, k, dim, s), k).groupBy("distance").count().collect()
    seen, total, radius = 0, sum(r["count"] for r in truth), s.bits
    for r in sorted(truth, key=lambda r: r["distance"]):
        seen += r["count"]
        if seen >= s.target * total:
            radius = r["distance"]
            break
    # the query set goes in blocks of a fixed number of rows, cut by id
    blocks = max(1, -(-asked.count() // s.query_block))
    edges = asked.approxQuantile("vec_id", [i / blocks for i in range(1, blocks)], 0.001) if blocks > 1 else []
    found = None
    for low, high in zip([None, *edges], [*edges, None]):
        part = asked
        part = part if low is None else part.where(F.col("vec_id") > low)
        part = part if high is None else part.where(F.col("vec_id") <= high)
        one = probe(rows, take(part.toArrow()), codes, None if exact else radius, k, dim, s)
        found = one if found is None else found.unionAll(one)
    return top_k(found, k).select("query_id", "rank", "vec_id", "score")
