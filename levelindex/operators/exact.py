"""Brute-force neighbours: the truth for recall, and the joins built on it."""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelindex.functions import distance

QUERY_BLOCK = 4096
#: Numbers of the queries of a block and of what they have found: each block reads the whole set once.
BLOCK_NUMBERS = 4 << 20
#: Up to so many neighbours the running ones are kept in place; beyond it all rows of a batch are sorted in.
FEW = 128


def rank(df: DataFrame, k: int, by: str = "qid") -> DataFrame:
    """The k nearest of each query; a row_number limit, so a part of it runs before the exchange."""
    w = Window.partitionBy(by).orderBy("dist", "vec_id")
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


#: Most queries of a plan that sends them all to every task; beyond it the block kernels take over.
BROADCAST_QUERIES = 100_000


def exact_knn(vs: DataFrame, qs: DataFrame, k: int, metric: str = "l2sq", digits: int | None = 6) -> DataFrame:
    """qid, vec_id, dist, rank by a plan that Catalyst holds whole, for query sets of a checked size; else by blocks."""
    if qs.count() > BROADCAST_QUERIES:
        found = exact_blocks(vs, qs, k, metric)
        return (found if digits is None else rank(found.drop("rank").withColumn("dist", F.round("dist", digits)), k)).select("qid", "vec_id", "dist", "rank")
    d = distance.score(metric, F.col("qvec"), F.col("vec"))
    d = d if digits is None else F.round(d, digits)
    pairs = vs.select("vec_id", "vec").crossJoin(F.broadcast(qs.select("qid", "qvec"))).select("qid", "vec_id", d.alias("dist"))
    return rank(pairs, k).select("qid", "vec_id", "dist", "rank")


def query_blocks(qs: DataFrame, size: int = QUERY_BLOCK, beside: int | None = None):
    """Queries as arrays, in blocks of a fixed number of rows; or, with `beside` numbers that a worker keeps beside each, of as many as a worker holds (`size` at least)."""
    rows, names = [], []
    for r in qs.select("qid", "qvec").toLocalIterator():
        names.append(r.qid)
        rows.append(r.qvec)
        if len(rows) == (size if beside is None else max(size, BLOCK_NUMBERS // (len(r.qvec) + beside))):
            yield np.array(names), np.array(rows, float)
            rows, names = [], []
    if rows:
        yield np.array(names), np.array(rows, float)


def columns_of(batch: pa.RecordBatch | pa.Table, vec: str = "vec") -> np.ndarray:
    lists = batch.column(vec)
    n = batch.num_rows
    lists = lists.combine_chunks() if isinstance(lists, pa.ChunkedArray) else lists
    return lists.flatten().to_numpy(zero_copy_only=False).reshape(n, -1).astype(float) if n else np.zeros((0, 1))


def exact_blocks(vs: DataFrame, qs: DataFrame, k: int, metric: str = "l2sq") -> DataFrame:
    """The same rows by block kernels: each task keeps k rows a query, then the tasks' rows are ranked."""
    spark = vs.sparkSession
    out = None
    for names, queries in query_blocks(qs, beside=2 * k if k <= FEW else None):
        if metric == "l2sq" and queries.shape[1] <= distance.BOX_DIMS:  # queries beside each other meet the same boxes
            order = np.concatenate(distance.boxes(queries, 1024)[0])
            names, queries = names[order], queries[order]
        sent = spark.sparkContext.broadcast((names, queries))

        def run(batches, sent=sent):
            qid, q = sent.value
            if k <= FEW:
                best = distance.Nearest(metric, q, k)
                for batch in batches:
                    if batch.num_rows:
                        best.add(batch.column("vec_id").to_numpy(), columns_of(batch))
                best.flush()
                row, place = np.nonzero(best.ids != best.NONE)
                yield pa.RecordBatch.from_arrays([pa.array(qid[row]), pa.array(best.ids[row, place]), pa.array(best.dist[row, place])], ["qid", "vec_id", "dist"])
                return
            ids, dist = np.zeros((len(qid), 0), np.int64), np.zeros((len(qid), 0))
            for batch in batches:
                if not batch.num_rows:
                    continue
                d = distance.block(metric, q, columns_of(batch))
                ids = np.concatenate([ids, np.broadcast_to(batch.column("vec_id").to_numpy(), d.shape)], axis=1)
                dist = np.concatenate([dist, d], axis=1)
                order = np.lexsort((ids, dist), axis=1)[:, :k]
                ids, dist = np.take_along_axis(ids, order, 1), np.take_along_axis(dist, order, 1)
            if ids.size:
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(qid, ids.shape[1])), pa.array(ids.ravel()), pa.array(dist.ravel())], ["qid", "vec_id", "dist"])

        part = vs.select("vec_id", "vec").mapInArrow(run, "qid long, vec_id long, dist double")
        out = part if out is None else out.unionAll(part)
    if out is None:
        return spark.createDataFrame([], "qid long, vec_id long, dist double, rank int")
    return rank(out, k)


#: Numbers of a set that goes whole to every worker.
HELD_NUMBERS = 8 << 20


def held_nearest(vs: DataFrame, qs: DataFrame, k: int, metric: str = "l2sq") -> DataFrame:
    """The rows of `exact_blocks` the other way round: the set goes to the workers and any number of queries pass by where they are; a set too large for that meets blocks of queries."""
    held = vs.agg(F.count("*").alias("n"), F.max(F.size("vec")).alias("d")).first()
    if not held["n"] or held["n"] * held["d"] > HELD_NUMBERS or k > FEW:
        return exact_blocks(vs, qs, k, metric)
    rows = vs.select("vec_id", "vec").toArrow()
    ids, x = rows.column("vec_id").to_numpy(), columns_of(rows)
    boxed = metric == "l2sq" and x.shape[1] <= distance.BOX_DIMS and len(x) >= 2048
    sent = vs.sparkSession.sparkContext.broadcast((ids, x, distance.boxes(x, 512 if k > 1 else 128) if boxed else None))

    def answers(qid, q):
        ids, x, tree = sent.value
        for some, reached in distance.near_boxes(q, tree, 1024 if k > 1 else 256) if boxed else ((np.arange(at, min(at + 1024, len(q))), None) for at in range(0, len(q), 1024)):
            best = distance.Nearest(metric, q[some], k)
            best.waiting.append((ids, x))
            best.flush(reached)
            row, place = np.nonzero(best.ids != best.NONE)
            yield qid[some[row]], best.ids[row, place], best.dist[row, place]

    def run(batches):
        waiting, count = [], 0
        for batch in itertools.chain(batches, [None]):
            if batch is not None and batch.num_rows:
                waiting.append((batch.column("qid").to_numpy(), columns_of(batch, "qvec")))
                count += waiting[-1][1].size
            if count >= distance.Nearest.HELD // 4 or (batch is None and waiting):  # many queries have more beside them
                found = [np.concatenate(c) for c in zip(*answers(*(np.concatenate(c) for c in zip(*waiting))))]
                waiting, count = [], 0
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in found], ["qid", "vec_id", "dist"])

    return rank(qs.select("qid", "qvec").mapInArrow(run, "qid long, vec_id long, dist double"), k)


def range_blocks(vs: DataFrame, qs: DataFrame, radius: float, metric: str = "l2sq") -> DataFrame:
    """All pairs within a radius by block kernels: pairs farther apart never leave a task, and those whose lengths differ by more do not meet."""
    spark = vs.sparkSession
    out = spark.createDataFrame([], "qid long, vec_id long, dist double")
    for names, queries in query_blocks(qs, 8 * QUERY_BLOCK):
        norms = np.sqrt((queries * queries).sum(1))
        order = np.argsort(norms, kind="stable")
        sent = spark.sparkContext.broadcast((names[order], queries[order], norms[order]))

        def run(batches, sent=sent):
            qid, q, size = sent.value
            for batch in batches:
                x, ids = columns_of(batch), batch.column("vec_id").to_numpy()
                own = np.sqrt((x * x).sum(1))
                order = np.argsort(own, kind="stable")
                for at in range(0, batch.num_rows, 512):
                    some = order[at : at + 512]
                    low, high = 0, len(q)
                    if metric == "l2sq":  # lengths differ by no more than the vectors do
                        reach = max(radius, 0) ** 0.5 * (1 + 1e-9) + 1e-9 * (1 + own[some[-1]])
                        low, high = np.searchsorted(size, own[some[0]] - reach), np.searchsorted(size, own[some[-1]] + reach, "right")
                    for start in range(low, high, QUERY_BLOCK):
                        part = q[start : min(start + QUERY_BLOCK, high)]
                        if metric == "l2sq":
                            slack = 1e-9 * (1 + size[min(start + QUERY_BLOCK, high) - 1] ** 2 + own[some[-1]] ** 2)
                            i, j = np.nonzero(distance.fast_l2sq(part, x[some]) <= radius + slack)
                            d = np.concatenate([np.einsum("xd,xd->x", g, g) for g in (part[i[n : n + 65536]] - x[some[j[n : n + 65536]]] for n in range(0, max(len(i), 1), 65536))])
                            near = d <= radius
                            i, j, d = i[near], j[near], d[near]
                        else:
                            d = distance.block(metric, part, x[some])
                            i, j = np.nonzero(d <= radius)
                            d = d[i, j]
                        yield pa.RecordBatch.from_arrays([pa.array(qid[start + i]), pa.array(ids[some[j]]), pa.array(d)], ["qid", "vec_id", "dist"])

        out = out.unionAll(vs.select("vec_id", "vec").mapInArrow(run, "qid long, vec_id long, dist double"))
    return out


def classes(links: DataFrame) -> DataFrame:
    """node, root (its smallest node) of all nodes with a link (a, b): least labels around, then labels of labels."""
    from levelindex import scratch

    both = scratch.save(links.select("a", "b").union(links.select("b", "a")).distinct(), "edges")
    labels = scratch.save(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("root")), "labels")
    while True:
        around = both.join(labels.select(F.col("node").alias("b"), F.col("root").alias("r")), "b").groupBy(F.col("a").alias("node")).agg(F.min("r").alias("r"))
        less = scratch.save(labels.join(around, "node").select("node", F.least("root", "r").alias("root"), F.col("root").alias("old")), "less")
        jump = less.select(F.col("node").alias("root"), F.col("root").alias("further"))
        new = scratch.save(less.join(jump, "root").select("node", F.col("further").alias("root"), "old"), "labels")
        if new.where("root != old").isEmpty():
            return new.select("node", "root")
        labels = new.select("node", "root")


#: Most centroids that a worker holds to rank them whole, as with a root.
MOST_CENTRES = 1_000_000


def centre_ranks(centres: DataFrame, qs: DataFrame, want: DataFrame) -> DataFrame:
    """qid, pid, rank of the wanted (qid, pid): the place of that centroid among all by distance from the query, ties to the smaller id."""
    ids, c = held_centres(centres)
    sent = qs.sparkSession.sparkContext.broadcast((ids, c))

    def run(batches):
        ids, c = sent.value
        for batch in batches:
            asks, q = batch.column("pids").to_pylist(), columns_of(batch, "qvec")
            names, pids, ranks = [], [], []
            for i, (qid, wanted) in enumerate(zip(batch.column("qid").to_pylist(), asks)):
                d = distance.block("l2sq", q[i : i + 1], c)[0]
                for pid in wanted:
                    at = int(np.searchsorted(ids, pid))
                    names.append(qid)
                    pids.append(pid)
                    ranks.append(1 + int((d < d[at]).sum()) + int((d[:at] == d[at]).sum()))
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(pids, pa.int64()), pa.array(ranks, pa.int64())], ["qid", "pid", "rank"])

    grouped = want.groupBy("qid").agg(F.collect_list("pid").alias("pids")).join(qs, "qid").select("qid", "qvec", "pids")
    return grouped.mapInArrow(run, "qid long, pid long, rank long")


def nearest_sum(centres: DataFrame, qs: DataFrame, m: int, sizes: DataFrame) -> DataFrame:
    """qid, n: what the m partitions of nearest centroids hold together (sizes: pid, n), ties to the smaller id."""
    ids, c = held_centres(centres)
    held = sizes.orderBy("pid").toArrow()
    n = np.zeros(len(ids), np.int64)
    n[np.searchsorted(ids, held.column("pid").to_numpy())] = held.column("n").to_numpy()
    sent = qs.sparkSession.sparkContext.broadcast((c, n))

    def run(batches):
        c, n = sent.value
        most = min(m, len(n))
        for batch in batches:
            q, sums = columns_of(batch, "qvec"), []
            for i in range(batch.num_rows):
                d = distance.block("l2sq", q[i : i + 1], c)[0]
                last = np.partition(d, most - 1)[most - 1]
                near = d < last
                sums.append(int(n[near].sum() + n[np.flatnonzero(d == last)[: most - int(near.sum())]].sum()))
            yield pa.RecordBatch.from_arrays([batch.column("qid"), pa.array(sums, pa.int64())], ["qid", "n"])

    return qs.select("qid", "qvec").mapInArrow(run, "qid long, n long")


def held_centres(centres: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    if centres.count() > MOST_CENTRES:
        raise ValueError(f"over {MOST_CENTRES} centroids; rank them level by level")
    rows = centres.select("vec_id", "vec").orderBy("vec_id").toArrow()
    return rows.column("vec_id").to_numpy(), columns_of(rows)


def least_budget(ranks: DataFrame, tenths: int, total: int) -> int | None:
    """The smallest rank up to which `tenths` tenths of `total` wanted places lie."""
    need = ranks.groupBy("rank").agg(F.count("*").alias("h"))
    run = need.withColumn("got", F.sum("h").over(Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)))
    return run.where(F.col("got") * 10 >= F.lit(tenths * total)).agg(F.min("rank")).first()[0]


def filtered_knn(vs: DataFrame, qs: DataFrame, k: int, where: Column, strategy: str = "pre", expand: int = 4, metric: str = "l2sq") -> DataFrame:
    """`pre` filters before the ranking; `post` ranks k * expand rows first, so it may give fewer."""
    if strategy == "pre":
        return exact_knn(vs.where(where), qs, k, metric)
    if strategy != "post":
        raise ValueError("the strategy is 'pre' or 'post'")
    wide = exact_knn(vs, qs, k * expand, metric).drop("rank")
    return rank(wide.join(vs.where(where).select("vec_id"), "vec_id", "left_semi"), k).select("qid", "vec_id", "dist", "rank")


def recall(found: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Mean share of each query's true neighbours among the found rows."""
    by = by or []
    hit = truth.select("qid", "vec_id").join(found.select(*by, "qid", "vec_id").distinct(), ["qid", "vec_id"])
    total = truth.count()
    return hit.groupBy(*by).agg((F.count("*") / F.lit(total)).alias("recall"))
