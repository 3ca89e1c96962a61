"""Inserts, deletes, splits, merges and reassignment: on one table of members, and on a leveled index.

`maintain` takes changes up an index: the partitions they touch at the leaf are written anew as a
further version, the centroids that came or went so are the changes of the level above, and at the
top the root and its graph follow.  Partitions that nothing touched are neither read nor written,
but for the sizes, and the keys where deletes look for their partitions.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.functions import distance
from levelindex.operators.cluster import MEMBERS, lloyd
from levelindex.operators.build import LeveledIndex
from levelindex.operators.cluster import local_cluster
from levelindex.operators.exact import columns_of, exact_blocks, held_nearest, rank
from levelindex.operators.graph import updated_graph
from levelindex.operators.search import descend
from levelindex.sources import store


def centroids(members: DataFrame) -> DataFrame:
    return members.where("pid = vec_id").select("pid", F.col("vec").alias("centre")).dropDuplicates(["pid"])


def nearest_partition(centres: DataFrame, vs: DataFrame, exclude_self: bool = False) -> DataFrame:
    """pid, vec_id, vec: the partition of the nearest centroid, ties to the smaller pid."""
    asked = vs.select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
    pool = centres.select(F.col("pid").alias("vec_id"), F.col("centre").alias("vec"))
    if exclude_self:
        found = held_nearest(pool, asked, 2).where("vec_id != qid").drop("rank")
        found = rank(found, 1)
    else:
        found = held_nearest(pool, asked, 1)
    return found.select(F.col("vec_id").alias("pid"), F.col("qid").alias("vec_id")).join(vs.select("vec_id", "vec"), "vec_id").select("pid", "vec_id", "vec")


def insert(members: DataFrame, new: DataFrame) -> DataFrame:
    """New vectors go to the leaf partition that a search finds; an id that is there already is replaced unless it is a centroid."""
    routed = nearest_partition(centroids(members), new)
    others = members.join(new.select("vec_id"), "vec_id", "left_anti").unionByName(members.where("pid = vec_id").join(new.select("vec_id"), "vec_id", "left_semi").select("pid", "vec_id", "vec"))
    fresh = routed.join(members.where("pid = vec_id").select("vec_id"), "vec_id", "left_anti")
    return others.select("pid", "vec_id", "vec").unionByName(fresh.select("pid", "vec_id", "vec"))


def delete(found_or_members: DataFrame, dead: DataFrame) -> DataFrame:
    """Tombstones hide vectors from every result; a deleted centroid goes on routing until its partition is rewritten."""
    return found_or_members.join(dead.select("vec_id").distinct(), "vec_id", "left_anti")


def split_oversize(members: DataFrame, most: int) -> DataFrame:
    """Partitions over the limit are cut in two around new medoids; repeated by the caller until none is left."""
    sizes = members.groupBy("pid").agg(F.count("*").alias("n"))
    big = sizes.where(F.col("n") > most).select("pid")

    def cut(table: pa.Table) -> pa.Table:
        ids = table.column("vec_id").to_numpy()
        x = columns_of(table)
        medoid, own = lloyd(x, ids, 2, 8)
        return pa.table({"pid": ids[medoid][own], "vec_id": ids, "vec": table.column("vec")})

    halves = members.join(big, "pid", "left_semi").groupBy("pid").applyInArrow(cut, MEMBERS)
    return members.join(big, "pid", "left_anti").select("pid", "vec_id", "vec").unionByName(halves)


def merge_undersize(members: DataFrame, least: int) -> DataFrame:
    """Members of small partitions go to the nearest centroid among those that stay."""
    sizes = members.groupBy("pid").agg(F.count("*").alias("n"))
    small = sizes.where(F.col("n") < least).select("pid")
    staying = members.join(small, "pid", "left_anti").select("pid", "vec_id", "vec")
    moved = nearest_partition(centroids(staying), members.join(small, "pid", "left_semi").select("vec_id", "vec"))
    return staying.unionByName(moved)


def reassign(members: DataFrame, changed: DataFrame, around: int = 4) -> DataFrame:
    """Members of changed partitions and of those next to them move to a nearer centroid, if there is one."""
    centres = centroids(members)
    asked = centres.join(changed.select("pid").distinct(), "pid", "left_semi").select(F.col("pid").alias("qid"), F.col("centre").alias("qvec"))
    near = exact_blocks(centres.select(F.col("pid").alias("vec_id"), F.col("centre").alias("vec")), asked, around + 1).select(F.col("vec_id").alias("pid")).distinct()
    local = members.join(near, "pid", "left_semi")
    pool = centres.join(near, "pid", "left_semi")
    moved = nearest_partition(pool, local.where("pid != vec_id").select("vec_id", "vec"))
    return members.join(near, "pid", "left_anti").select("pid", "vec_id", "vec").unionByName(local.where("pid = vec_id").select("pid", "vec_id", "vec")).unionByName(moved)


def partition_search(members: DataFrame, qs: DataFrame, k: int, m: int, metric: str = "l2sq") -> DataFrame:
    """One level over a member table: nearest m centroids, then their members."""
    pool = centroids(members).select(F.col("pid").alias("vec_id"), F.col("centre").alias("vec"))
    near = exact_blocks(pool, qs, m, metric).select("qid", F.col("vec_id").alias("pid"))
    found = near.join(qs, "qid").join(members, "pid").select("qid", "vec_id", distance.score(metric, F.col("qvec"), F.col("vec")).alias("dist"))
    return rank(found, k)


def upward(members: DataFrame, upper: DataFrame) -> DataFrame:
    """The upper level after changes below: gone centroids leave, new ones enter the nearest upper partition."""
    now = members.where("pid = vec_id").select("vec_id", "vec").dropDuplicates(["vec_id"])
    kept = upper.join(now.select("vec_id"), "vec_id", "left_semi")
    heads = upper.where("pid = vec_id")
    routing = heads.select("pid", F.col("vec").alias("centre"))
    new = now.join(upper.select("vec_id"), "vec_id", "left_anti")
    return kept.select("pid", "vec_id", "vec").unionByName(nearest_partition(routing, new))


def last_change(changes: DataFrame) -> DataFrame:
    """The latest change of each vector (op, vec_id, vec, ts); equal times: a delete wins."""
    w = Window.partitionBy("vec_id").orderBy(F.desc("ts"), F.col("op"))
    return changes.withColumn("n", F.row_number().over(w)).where("n = 1").drop("n")


# --- the leveled index ---

def route(index: LeveledIndex, vs: DataFrame, level: int, m: int = 16) -> DataFrame:
    """pid, vec_id, vec: the partition of a level for each vector, by the index's own search above it."""
    asked = vs.select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
    found, _ = descend(index, asked, 1, m, root="exact", stop=level + 1)
    return found.select(F.col("vec_id").alias("pid"), F.col("qid").alias("vec_id")).join(vs.select("vec_id", "vec"), "vec_id").select("pid", "vec_id", "vec")


def dealt_out(rows: DataFrame, most: int) -> DataFrame:
    """Whole partitions are dealt out in runs of at most `most` along their widest component; each run's middle vector is its centroid."""

    def cut(table: pa.Table) -> pa.Table:
        ids, x = table.column("vec_id").to_numpy(), columns_of(table)
        order = np.lexsort((ids, x[:, int(np.ptp(x, axis=0).argmax())]))
        pid = np.empty_like(ids)
        for run in np.array_split(order, -(-len(ids) // most)):
            pid[run] = ids[run[len(run) // 2]]
        return pa.table({"pid": pid, "vec_id": ids, "vec": table.column("vec")})

    return rows.select("pid", "vec_id", "vec").groupBy("pid").applyInArrow(cut, MEMBERS)


def even_parts(rows: DataFrame, most: int) -> DataFrame:
    """Partitions that clustering left over `most` members are dealt out, the others stay."""
    big = rows.groupBy("pid").agg(F.count("*").alias("n")).where(F.col("n") > most).select("pid")
    big = F.broadcast(scratch.save(big, "oversize"))
    return rows.join(big, "pid", "left_anti").select("pid", "vec_id", "vec").unionByName(dealt_out(rows.join(big, "pid", "left_semi"), most))


def changed_partitions(index: LeveledIndex, level: int, add: DataFrame, gone: DataFrame, most: int, least: int, m: int, rounds: int = 8) -> tuple[DataFrame, DataFrame]:
    """The rows of all partitions that the changes touch, as they are afterwards, and the pids that are no longer as they were.

    Vectors that come take the place of those with their ids.  A partition whose centroid went, or with
    over `most` members, is clustered anew; one with under `least` members is dealt to the nearest others.
    Equal vectors can't be clustered, so a partition over `most` with nothing else is dealt out at once.
    """
    old = index.members(level)
    away = gone.select("vec_id").union(add.select("vec_id")).distinct()
    routed = scratch.save(route(index, add, level, m), "routed")
    homes = old.select("pid", "vec_id").join(away, "vec_id", "left_semi").select("pid")
    sizes = index.packed(level).select("pid", "n").where((F.col("n") > most) | (F.col("n") < least)).select("pid")
    region = scratch.save(routed.select("pid").union(homes).union(sizes).distinct(), "region")
    rows = scratch.save(old.join(region, "pid", "left_semi").join(away, "vec_id", "left_anti").select("pid", "vec_id", "vec").unionByName(routed), "rows")
    settled = []
    for _ in range(rounds):
        look = F.xxhash64("vec")
        per = rows.groupBy("pid").agg(F.count("*").alias("n"), F.max((F.col("pid") == F.col("vec_id")).cast("int")).alias("head"), (F.min(look) == F.max(look)).alias("equal"))
        odd = scratch.save(per.where((F.col("n") > most) | (F.col("head") == 0)).select("pid", "n", "equal"), "odd")
        if odd.isEmpty():
            break
        settled.append(scratch.save(rows.join(odd, "pid", "left_anti"), "settled"))
        whole = scratch.save(rows.join(odd, "pid").select(F.col("pid").alias("cell"), "vec_id", "vec", "n", "equal"), "odd-rows")
        few, many, equal = whole.where(F.col("n") <= most), whole.where((F.col("n") > most) & ~F.col("equal")), whole.where((F.col("n") > most) & F.col("equal"))
        again = local_cluster(many, min(1.0, 2 / most)).unionByName(local_cluster(few, 1e-9)).unionByName(dealt_out(equal.withColumnRenamed("cell", "pid"), most))
        rows = scratch.save(again, "rows")
    else:
        rows = scratch.save(even_parts(rows, most), "rows")
    for part in settled:
        rows = rows.unionByName(part)
    small = scratch.save(rows.groupBy("pid").agg(F.count("*").alias("n")).where(F.col("n") < least).select("pid"), "small")
    if not small.isEmpty():
        heads = old.where("pid = vec_id").join(region, "pid", "left_anti").select("pid", F.col("vec").alias("centre")).unionByName(centroids(rows.join(small, "pid", "left_anti")))
        if not heads.isEmpty():
            moved = scratch.save(nearest_partition(heads, rows.join(small, "pid", "left_semi").select("vec_id", "vec")), "moved")
            joined = old.join(moved.select("pid").distinct(), "pid", "left_semi").join(region, "pid", "left_anti").select("pid", "vec_id", "vec")
            region = scratch.save(region.union(moved.select("pid")).distinct(), "region")
            rows = scratch.save(rows.join(small, "pid", "left_anti").unionByName(joined).unionByName(moved), "rows")
    return rows, scratch.save(region.union(rows.select("pid")).distinct(), "touched")


def maintain(index: LeveledIndex, add: DataFrame | None = None, gone: DataFrame | None = None, most: int = 40, least: int = 2, m: int = 16, path: str | None = None) -> LeveledIndex:
    """The index after inserts (vec_id, vec) and deletes (vec_id), with its partitions within their sizes; the old one stays readable."""
    spark, path = index.spark, path or scratch.path(index.spark, "version")
    if path in index.versions:
        raise ValueError("a version of the index is not written over")
    empty = spark.createDataFrame([], "vec_id long, vec array<double>")
    add = empty if add is None else add.select("vec_id", "vec").dropDuplicates(["vec_id"])
    gone = empty.select("vec_id") if gone is None else gone.select("vec_id").distinct()
    buckets = []
    for level in range(index.levels - 1):
        rows, touched = changed_partitions(index, level, add, gone, most, least, m)
        buckets.append(store.buckets_for(spark, rows.count()))
        store.write_level(rows, path, level, buckets[-1], index.width)
        store.write_touched(touched, path, level)
        was = index.members(level).where("pid = vec_id").join(touched, "pid", "left_semi").select("vec_id", "vec")
        now = rows.where("pid = vec_id").select("vec_id", "vec")
        gone = scratch.save(was.select("vec_id").join(now.select("vec_id"), "vec_id", "left_anti"), "gone")
        add = scratch.save(now.join(was, ["vec_id", "vec"], "left_anti").select("vec_id", "vec"), "add")
    away = gone.select("vec_id").union(add.select("vec_id"))
    store.write_root(index.root().join(away, "vec_id", "left_anti").unionByName(add), path)
    out = LeveledIndex(spark, path, [], [], index.metric, index.graph_settings, [*index.buckets, buckets], index.width, [*index.versions, path])
    for level in range(index.levels - 1):
        n, p = out.packed(level).agg(F.sum("n"), F.count("*")).first()
        out.counts.append(n or 0)
        out.partitions.append(p)
    out.counts.append(out.root().count())
    if index._graph is not None:  # of the root's size at most
        new, old = add.orderBy("vec_id").toArrow(), gone.toArrow()
        out._graph = updated_graph(index._graph, new.column("vec_id").to_numpy(), columns_of(new), old.column("vec_id").to_numpy())
    out.save_manifest()
    return out


def compact(index: LeveledIndex) -> LeveledIndex:
    """One version again, with buckets over whole levels."""
    spark, path = index.spark, scratch.path(index.spark, "index")
    buckets = [store.buckets_for(spark, n) for n in index.counts[:-1]]
    for level, n in enumerate(buckets):
        store.write_level(index.members(level), path, level, n, index.width)
    store.write_root(index.root(), path)
    out = LeveledIndex(spark, path, index.counts, index.partitions, index.metric, index.graph_settings, [buckets], index.width)
    out.save_manifest()
    return out
