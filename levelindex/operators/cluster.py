"""Partitioning: coarse cells, boundary copies, clustering inside cells, merging of equal partitions."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.functions import distance
from levelindex.operators.exact import columns_of, query_blocks

#: Most coarse centroids that a driver holds and sends; with more cells the coarse step must be leveled itself.
MOST_CELLS = 4096
CELL_ROWS = 20_000
#: No cell is clustered in one task beyond this; larger ones are split first, by themselves.
CELL_MOST = 60_000
MEMBERS = "pid long, vec_id long, vec array<double>"


def density(members: DataFrame) -> DataFrame:
    """Partitions per vector by level (a level column, if there is one)."""
    by = [c for c in ("level",) if c in members.columns]
    out = members.groupBy(*by).agg(F.countDistinct("pid").alias("n_partitions"), F.countDistinct("vec_id").alias("n_vectors"))
    return out.withColumn("density", F.col("n_partitions") / F.col("n_vectors"))


def size_stats(members: DataFrame) -> DataFrame:
    return members.groupBy("pid").agg(F.count("*").alias("n")).agg(F.count("*").alias("partitions"), F.min("n").alias("least"), F.max("n").alias("most"), F.avg("n").alias("mean"))


def hash_sample(vs: DataFrame, n: int, seed: int) -> DataFrame:
    """The n rows of smallest hash: the same rows whatever the partitioning."""
    return vs.orderBy(F.xxhash64("vec_id", F.lit(seed)), "vec_id").limit(n)


def coarse_kmeans(vs: DataFrame, cells: int, rounds: int = 4, seed: int = 1) -> np.ndarray:
    """Centroids of a distributed Lloyd iteration: workers send sums by cell, the driver keeps `cells` centroids."""
    if not 1 <= cells <= MOST_CELLS:
        raise ValueError(f"between 1 and {MOST_CELLS} cells")
    start = hash_sample(vs, cells, seed).select("vec").toArrow()
    if not start.num_rows:
        return np.zeros((0, 1))
    centres = np.array(start.column("vec").to_pylist(), float)
    for _ in range(rounds if len(centres) > 1 else 0):
        sent = vs.sparkSession.sparkContext.broadcast(centres)

        def run(batches, sent=sent):
            c = sent.value
            total, count = np.zeros_like(c), np.zeros(len(c), np.int64)
            for batch in batches:
                x = columns_of(batch)
                if len(x):
                    own = distance.nearest_centre(x, c)
                    total += distance.sums_by(own, x, len(c))
                    count += np.bincount(own, minlength=len(c))
            at = np.flatnonzero(count)
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(count[at]), pa.array(list(total[at]), pa.list_(pa.float64()))], ["cell", "n", "total"])

        sums = vs.select("vec").mapInArrow(run, "cell int, n long, total array<double>").select("cell", "n", F.posexplode("total"))
        rows = sums.groupBy("cell", "pos").agg((F.sum("col") / F.sum("n")).alias("mean")).collect()
        centres = centres.copy()
        for r in rows:
            centres[r["cell"], r["pos"]] = r["mean"]
        sent.unpersist()
    return centres


def replicate_boundary(vs: DataFrame, centres: np.ndarray, eps: float = 0.1, max_copies: int = 2) -> DataFrame:
    """cell, vec_id, vec, is_copy: the nearest cell, and further ones within (1 + eps) of its distance."""
    sent = vs.sparkSession.sparkContext.broadcast(centres)

    def run(batches):
        c = sent.value
        n = min(max(1, max_copies), len(c))
        for batch in batches:
            if not batch.num_rows:
                continue
            if n == 1:
                own = pa.array(distance.nearest_centre(columns_of(batch), c).astype(np.int32))
                yield pa.RecordBatch.from_arrays([own, batch.column("vec_id"), batch.column("vec"), pa.array(np.zeros(batch.num_rows, bool))], ["cell", "vec_id", "vec", "is_copy"])
                continue
            d = np.sqrt(distance.fast_l2sq(columns_of(batch), c))
            near = np.argsort(d, axis=1, kind="stable")[:, :n]
            value = np.take_along_axis(d, near, 1)
            keep = value <= (1 + eps) * value[:, :1]
            keep[:, 0] = True
            row, place = np.nonzero(keep)
            at = pa.array(row)
            yield pa.RecordBatch.from_arrays([pa.array(near[row, place].astype(np.int32)), batch.column("vec_id").take(at), batch.column("vec").take(at), pa.array(place > 0)], ["cell", "vec_id", "vec", "is_copy"])

    return vs.select("vec_id", "vec").mapInArrow(run, "cell int, vec_id long, vec array<double>, is_copy boolean")


def lloyd(x: np.ndarray, ids: np.ndarray, k: int, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """Medoid rows and the medoid of each row; ties to the smaller id, empty clusters dropped."""
    order = np.argsort(ids, kind="stable")
    x, n = x[order], len(x)
    k = max(1, min(k, n))
    pick = np.random.default_rng(n * 31 + k).permutation(n)[:k]
    c = x[np.sort(pick)].copy()
    tree = distance.boxes(x, 256) if x.shape[1] <= distance.BOX_DIMS and n >= 1024 else None
    for _ in range(rounds):
        own = distance.nearest_centre(x, c, tree=tree)
        count = np.bincount(own, minlength=len(c))
        total = distance.sums_by(own, x, len(c))
        used = count > 0
        c[used] = total[used] / count[used, None]
    own = distance.nearest_centre(x, c, tree=tree)
    d = ((x - c[own]) ** 2).sum(axis=1)
    by = np.lexsort((np.arange(n), d, own))
    first = by[np.concatenate(([True], own[by][1:] != own[by][:-1]))]
    medoid = np.sort(first)
    own = distance.nearest_centre(x, x[medoid], tree=tree)
    own[medoid] = np.arange(len(medoid))  # a medoid stays in its own partition, equal vectors or not
    back = np.empty(n, np.int64)
    back[order] = own
    return order[medoid], back


def local_cluster(cells: DataFrame, share: float, algorithm: str = "lloyd", rounds: int = 6, named: bool = False) -> DataFrame:
    """pid, vec_id, vec (and the cell, if `named`): each cell clustered alone; pid is the key of the partition's medoid.

    `stride` takes every (1 / share)-th key as centroid in the whole set, for results that SQL can repeat.
    """
    if not 0 < share <= 1:
        raise ValueError("the density lies in (0, 1]")
    if algorithm == "stride":
        return stride_members(cells, round(1 / share))

    def run(table: pa.Table) -> pa.Table:
        ids = table.column("vec_id").to_numpy()
        x = columns_of(table)
        medoid, own = lloyd(x, ids, max(1, round(len(ids) * share)), rounds)
        return pa.table({"pid": ids[medoid][own], "vec_id": ids, "vec": table.column("vec")} | ({"cell": table.column("cell")} if named else {}))

    bounded = bounded_cells(cells.select(F.col("cell").cast("string").alias("cell"), "vec_id", "vec"))
    return bounded.groupBy("cell").applyInArrow(run, MEMBERS + (", cell string" if named else ""))


def bounded_cells(cells: DataFrame, most: int = CELL_MOST, fanout: int = 8) -> DataFrame:
    """cell, vec_id, vec with cells of at most about `most` rows. A larger cell is dealt to the nearest of `fanout` of its vectors; one that does not get smaller so (equal vectors) is dealt by a hash. No task holds a large cell."""
    part = F.pmod(F.xxhash64("vec_id", F.lit(41)), F.lit(fanout)).cast("string")
    sizes = cells.groupBy("cell").agg(F.count("*").alias("n"))
    large = {r["cell"]: r["n"] for r in sizes.where(F.col("n") > most).collect()}  # at most rows / `most` names
    while large:
        names = list(large)
        cells = scratch.save(cells, "cells")
        whole, rest = cells.where(F.col("cell").isin(names)), cells.where(~F.col("cell").isin(names))
        seeds = whole.groupBy("cell", part.alias("s")).agg(F.min(F.struct(F.xxhash64("vec_id"), "vec")).alias("x")).groupBy("cell").agg(F.collect_list(F.struct("s", F.col("x.vec").alias("v"))).alias("seeds"))
        near = F.array_min(F.transform("seeds", lambda z: F.struct(distance.l2sq(F.col("vec"), z["v"]).alias("d"), z["s"].alias("s"))))["s"]
        placed = whole.join(F.broadcast(seeds), "cell").select(F.concat_ws(".", "cell", near).alias("cell"), "vec_id", "vec")
        placed = scratch.save(placed, "cells")
        sizes = {r["cell"]: r["count"] for r in placed.groupBy("cell").count().where(F.col("count") > most).collect()}
        stuck = [c for c, n in sizes.items() if n > 0.9 * large[c.rsplit(".", 1)[0]]]
        if stuck:
            placed = placed.withColumn("cell", F.when(F.col("cell").isin(stuck), F.concat_ws(".", F.col("cell"), F.lit("h"), part)).otherwise(F.col("cell")))
            sizes = {r["cell"]: r["count"] for r in placed.groupBy("cell").count().where(F.col("count") > most).collect()}
        cells, large = rest.unionByName(placed), sizes
    return cells


def stride_members(vs: DataFrame, stride: int) -> DataFrame:
    """Members of partitions whose centroids are the keys divisible by `stride`; ties to the smaller pid.

    Centroids go to the workers in blocks of a fixed number; each block leaves one candidate a vector.
    """
    centres = vs.where(F.pmod("vec_id", F.lit(stride)) == 0)
    best = None
    for names, block in query_blocks(centres.select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))):
        sent = vs.sparkSession.sparkContext.broadcast((names, block))

        def run(batches, sent=sent):
            names, c = sent.value
            for batch in batches:
                x = columns_of(batch)
                for at in range(0, batch.num_rows, 1024):
                    best = distance.Nearest("l2sq", x[at : at + 1024], 1)
                    best.add(names, c)
                    best.flush()
                    part = batch.slice(at, 1024)
                    yield pa.RecordBatch.from_arrays([pa.array(best.ids[:, 0]), part.column("vec_id"), part.column("vec"), pa.array(best.dist[:, 0])], ["pid", "vec_id", "vec", "d"])

        part = vs.select("vec_id", "vec").mapInArrow(run, "pid long, vec_id long, vec array<double>, d double")
        best = part if best is None else best.unionAll(part)
    if best is None:
        return vs.sparkSession.createDataFrame([], MEMBERS)
    if len(names) == centres.count():  # one block: nothing to choose between
        return best.select("pid", "vec_id", "vec")
    nearest = best.groupBy("vec_id").agg(F.min(F.struct("d", "pid")).alias("best"), F.first("vec").alias("vec"))
    return nearest.select(F.col("best.pid").alias("pid"), "vec_id", "vec")


def merge_equal(members: DataFrame) -> DataFrame:
    """Partitions of one pid from several cells become one; a member counts once."""
    return members.dropDuplicates(["pid", "vec_id"])


def keep_nearest_copy(members: DataFrame) -> DataFrame:
    """Of a vector's copies just the one nearest to its partition's medoid; a medoid stays at home."""
    centre = members.where("pid = vec_id").select("pid", F.col("vec").alias("centre")).dropDuplicates(["pid"])
    w = Window.partitionBy("vec_id").orderBy(F.col("pid") != F.col("vec_id"), "d", "pid")
    near = members.join(centre, "pid").withColumn("d", distance.l2sq(F.col("vec"), F.col("centre")))
    return near.withColumn("n", F.row_number().over(w)).where("n = 1").select("pid", "vec_id", "vec")


def coarse_centres(vs: DataFrame, cells: int | None = None, seed: int = 1) -> np.ndarray:
    """The coarse centroids of a set; they don't depend on the density, so one array serves partitionings at several."""
    if cells is None:
        cells = min(MOST_CELLS, max(1, math.ceil(vs.count() / CELL_ROWS)))
    return coarse_kmeans(vs, cells, seed=seed)


def partition(vs: DataFrame, share: float, cells: int | None = None, eps: float = 0.1, max_copies: int = 1, algorithm: str = "lloyd", rounds: int = 6, seed: int = 1, centres: np.ndarray | None = None) -> DataFrame:
    """Stages two to four of the build: cells (around `centres`, if the set's are known), copies, clustering inside cells, merging."""
    if algorithm == "stride":
        return stride_members(vs, round(1 / share))
    centres = coarse_centres(vs, cells, seed) if centres is None else centres
    placed = replicate_boundary(vs, centres, eps, max_copies)
    members = merge_equal(local_cluster(placed, share, algorithm, rounds))
    return keep_nearest_copy(scratch.save(members, "members")) if max_copies > 1 else members
