"""Batch search: root, then one join per level on pid, distances where the partitions are."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.functions import distance
from levelindex.operators.build import LeveledIndex
from levelindex.operators.exact import exact_blocks, held_nearest, rank
from levelindex.operators.graph import graph_search
from levelindex.sources.store import WIDTHS, flat_lists, unpack

CANDIDATES = "qid long, vec_id long, dist double"


def budgets(m, levels: int) -> list[int]:
    """One probe budget for all levels, or one for each level from the leaf up."""
    out = [m] * levels if isinstance(m, int) else list(m)
    if len(out) < levels or min(out) < 1:
        raise ValueError("a probe budget of at least 1 for every level below and at the root")
    return out


def root_candidates(index: LeveledIndex, qs: DataFrame, m: int, how: str) -> DataFrame:
    if how == "exact":
        return held_nearest(index.root(), qs, m, index.metric).select("qid", "vec_id", "dist")
    return graph_search(index.graph, qs, m, max(m, 32)).select("qid", "vec_id", "dist")


#: Queries of one partition are dealt to so many lanes, each a row of its own, so that a hot partition spreads.
LANES = 16


def scan_packed(metric: str, keep: int, width: str):
    """Kernel over (pid, qids, qvecs, n, ids, block) rows: per partition and query the `keep` nearest (an exact part of the limit)."""

    def run(batches):
        for batch in batches:
            found_q, found_v, found_d = [], [], []
            queries, q_at = flat_lists(batch.column("qids"))
            values, v_at = flat_lists(batch.column("qvecs"))
            n, ids, block = batch.column("n"), batch.column("ids"), batch.column("block")
            for i in range(batch.num_rows):
                names, vecs = unpack(n[i].as_py(), ids[i].as_py(), block[i].as_py(), width)
                asked = queries[q_at[i] : q_at[i + 1]]
                d = distance.block(metric, values[v_at[i] : v_at[i + 1]].reshape(len(asked), -1), vecs)
                at = distance.nearest_rows(d, names, keep)
                found_q.append(np.repeat(asked, at.shape[1]))
                found_v.append(names[at].ravel())
                found_d.append(np.take_along_axis(d, at, 1).ravel())
            if found_q:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found_q).astype(np.int64)), pa.array(np.concatenate(found_v)), pa.array(np.concatenate(found_d))], ["qid", "vec_id", "dist"])

    return run


def grouped_probes(asked: DataFrame, buckets: int) -> DataFrame:
    """One row for each partition and lane with its queries, dealt like the stored level: the only exchange of a round."""
    dealt = asked.select("pid", "qid", "qvec").repartition(buckets, "pid")
    lane = F.pmod(F.xxhash64("qid"), F.lit(LANES)).alias("lane")
    both = dealt.groupBy("pid", lane).agg(F.collect_list(F.struct("qid", "qvec")).alias("asks"))
    return both.select("pid", F.col("asks.qid").alias("qids"), F.flatten("asks.qvec").alias("qvecs"))


def probe_level(index: LeveledIndex, probes: DataFrame, qs: DataFrame, level: int, keep: int, mode: str, where: Column | None, copies: int, dead: DataFrame | None = None) -> DataFrame:
    """Candidates of one level for (qid, pid) probes."""
    asked = probes.join(qs, "qid")
    if mode == "near_data" and where is None and dead is None:
        sent = grouped_probes(asked, index.buckets[0][level])
        found = sent.hint("shuffle_hash").join(index.packed(level), "pid").select("pid", "qids", "qvecs", "n", "ids", "block").mapInArrow(scan_packed(index.metric, keep * copies, index.width), CANDIDATES)
    elif mode in ("near_data", "rows"):
        members = index.members(level) if where is None else index.members(level).where(where)
        members = members if dead is None else members.join(dead.select("vec_id").distinct(), "vec_id", "left_anti")
        found = asked.join(members, "pid").select("qid", "vec_id", distance.score(index.metric, F.col("qvec"), F.col("vec")).alias("dist"))
    elif mode == "raw_transfer":
        # whole partitions travel to the query's side, distances come after the exchange
        members = index.members(level) if where is None else index.members(level).where(where)
        members = members if dead is None else members.join(dead.select("vec_id").distinct(), "vec_id", "left_anti")
        raw = asked.select("qid", "pid").join(members, "pid").repartition("qid").join(qs.repartition("qid"), "qid")
        found = raw.select("qid", "vec_id", distance.score(index.metric, F.col("qvec"), F.col("vec")).alias("dist"))
    else:
        raise ValueError("the mode is 'near_data', 'rows' or 'raw_transfer'")
    if copies > 1:
        found = found.groupBy("qid", "vec_id").agg(F.min("dist").alias("dist"))
    return rank(found, keep)


def search(index: LeveledIndex, qs: DataFrame, k: int = 10, m=64, mode: str = "near_data", root: str = "graph", where: Column | None = None, copies: int = 1, dead: DataFrame | None = None) -> DataFrame:
    """qid, rank, vec_id, dist: root top-m, then each level's top-m, then the leaf's top-k; one plan, no action between levels.

    `dead` (vec_id) are tombstones: these vectors never come out, though deleted centroids still route.
    """
    if k < 1:
        raise ValueError("k is at least 1")
    return descend(index, qs, k, m, mode, root, where, copies, dead)[0]


def descend(index: LeveledIndex, qs: DataFrame, k: int, m, mode: str = "near_data", root: str = "graph", where: Column | None = None, copies: int = 1, dead: DataFrame | None = None, stop: int = 0, keep_probes: bool = False, start: DataFrame | None = None):
    """The result, and the probes of each level (qid, pid, level) for the measures; `stop` is the last level that is read.

    With `keep_probes` each round's probes are written, so that measures read them instead of searching again.
    `start` are ranked root candidates, m at least, so that searches with several budgets rank the root once.
    """
    below = index.levels - 1
    m = budgets(m, index.levels)
    if below <= stop:
        return rank(root_candidates(index, qs, k, root), k).select("qid", "rank", "vec_id", "dist"), []
    found = rank(root_candidates(index, qs, m[below], root), m[below]) if start is None else start.where(F.col("rank") <= m[below])
    log = []
    for level in range(below - 1, stop - 1, -1):
        probes = found.select("qid", F.col("vec_id").alias("pid"))
        probes = scratch.save(probes, "probes") if keep_probes else probes
        log.append(probes.withColumn("level", F.lit(level)))
        keep = k if level == stop else m[level]
        found = probe_level(index, probes, qs, level, keep, mode, where if level == 0 else None, copies, dead if level == 0 else None)
    return found.select("qid", "rank", "vec_id", "dist"), log


def trace(index: LeveledIndex, log: list[DataFrame], mode: str = "near_data", m: int = 64) -> DataFrame:
    """Per query and level: partitions and vectors read, bytes moved. Near the data each partition replies with at most m pairs of id and distance (12 bytes); else whole partitions travel."""
    dim = index.root().select(F.size("vec").alias("d")).first()["d"]
    out = None
    for level, probes in zip(range(index.levels - 2, -1, -1), log):
        sizes = index.packed(level).select("pid", "n")
        moved = 12 * F.least(F.col("n"), F.lit(m)) if mode == "near_data" else F.col("n") * (WIDTHS[index.width] * dim + 8)
        part = probes.join(sizes, "pid").groupBy("qid", "level").agg(F.count("*").alias("partitions_read"), F.sum("n").alias("vectors_read"), F.sum(moved).alias("bytes"))
        out = part if out is None else out.unionByName(part)
    return out


def tune_budget(index: LeveledIndex, qs: DataFrame, truth: DataFrame, k: int, target: float, m_max: int = 256, root: str = "graph") -> tuple[int, list[tuple[int, float]]]:
    """Smallest m that reaches the target recall: doubling, then halving of the interval, with a final confirmation."""
    total = truth.count()
    curve: dict[int, float] = {}

    def at(m: int) -> float:
        if m not in curve:
            curve[m] = search(index, qs, k, m, root=root).join(truth.select("qid", "vec_id"), ["qid", "vec_id"], "left_semi").count() / max(total, 1)
        return curve[m]

    high = 1
    while at(high) < target and high < m_max:
        high = min(2 * high, m_max)
    low = max(1, high // 2)
    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if at(mid) >= target else (mid + 1, high)
    at(high)
    return high, sorted(curve.items())


def level_truth(index: LeveledIndex, qs: DataFrame, m: int, k: int, base: DataFrame | None = None) -> list[DataFrame]:
    """(qid, vec_id) of each level's exact top-m (top-k at the leaf), from the root down to the leaf; written, for all indexes that share the levels. `base` is the indexed set, if it is at hand."""
    sets = [index.root()] + [index.members(level).select("vec_id", "vec").dropDuplicates(["vec_id"]) for level in range(index.levels - 2, -1, -1)]
    sets[-1] = sets[-1] if base is None else base
    return [scratch.save((held_nearest(vs, qs, m, index.metric) if at < len(sets) - 1 else exact_blocks(vs, qs, k, index.metric)).select("qid", "vec_id"), "want") for at, vs in enumerate(sets)]


def level_accuracy(index: LeveledIndex, qs: DataFrame, m: int, k: int | None = None, root: str = "graph", truth: list[DataFrame] | None = None) -> DataFrame:
    """Share of each level's exact top-m (top-k at the leaf) that the search admits; `truth` is the `level_truth` of this index or of a deeper one over the same levels."""
    k = k or m
    result, log = descend(index, qs, k, m, root=root, keep_probes=True)
    got = [log[i].select("qid", F.col("pid").alias("vec_id")) for i in range(len(log))] + [result.select("qid", "vec_id")]
    truth = truth or level_truth(index, qs, m, k)
    out = None
    for depth, (found, want) in enumerate(zip(got, truth[-len(got) :])):
        part = want.join(found.withColumn("hit", F.lit(1)), ["qid", "vec_id"], "left").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("accuracy")).withColumn("level", F.lit(len(got) - 1 - depth))
        out = part if out is None else out.unionByName(part)
    return out


def with_payload(found: DataFrame, payload: DataFrame, key: str) -> DataFrame:
    """Contents by id, joined after the ranking so that they never travel with candidates."""
    return found.join(payload.withColumnRenamed(key, "vec_id"), "vec_id", "left")


def access_skew(reads: DataFrame) -> DataFrame:
    """Smallest share of vectors that takes half of all accesses; reads: vec_id, n."""
    per_count = reads.groupBy("n").agg(F.count("*").alias("c"))
    run = Window.orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, 0)
    summed = per_count.withColumn("taken", F.sum(F.col("n") * F.col("c")).over(run)).withColumn("rows", F.sum("c").over(run))
    total = per_count.agg(F.sum(F.col("n") * F.col("c")).alias("t"), F.sum("c").alias("r"))
    return summed.crossJoin(F.broadcast(total)).where("2 * taken >= t").agg((F.min("rows") / F.max("r")).alias("share"))
