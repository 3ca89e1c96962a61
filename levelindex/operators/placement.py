"""Where partitions live: hashes, a ring, clusters; and what a probe log then costs each node."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelindex.functions import distance
from levelindex.operators.cluster import coarse_kmeans
from levelindex.operators.exact import columns_of

RING = 1 << 32


def md5_number(col):
    return F.conv(F.substring(F.md5(col.cast("string")), 1, 8), 16, 10).cast("long")


def place_hash(pids: DataFrame, nodes: int, fn: str = "xxhash64") -> DataFrame:
    if nodes < 1:
        raise ValueError("at least one node")
    h = F.xxhash64("pid") if fn == "xxhash64" else md5_number(F.col("pid"))
    return pids.select("pid", F.pmod(h, F.lit(nodes)).cast("int").alias("node"))


def ring_points(spark, nodes: int, vnodes: int) -> DataFrame:
    """Ring positions of virtual nodes; a fixed, small table."""
    own = spark.range(nodes).select(F.col("id").cast("int").alias("node"), F.explode(F.sequence(F.lit(0), F.lit(vnodes - 1))).alias("v"))
    return own.select("node", md5_number(F.concat_ws(":", "node", "v")).alias("at"))


def place_ring(pids: DataFrame, nodes: int, vnodes: int = 64) -> DataFrame:
    """Consistent hashing: the first virtual node at or after the pid's position, the smallest one past the end."""
    points = ring_points(pids.sparkSession, nodes, vnodes).agg(F.array_sort(F.collect_list(F.struct("at", "node"))).alias("ring"))
    spot = pids.select("pid", md5_number(F.col("pid")).alias("at")).crossJoin(F.broadcast(points))
    after = F.filter("ring", lambda p: p["at"] >= F.col("at"))
    return spot.select("pid", F.coalesce(F.get(after, F.lit(0)), F.get("ring", F.lit(0)))["node"].alias("node"))


def grow(pids: DataFrame, nodes: int, more: int, vnodes: int = 64) -> DataFrame:
    """Old and new node of each pid when nodes join the ring."""
    return place_ring(pids, nodes, vnodes).withColumnRenamed("node", "old").join(place_ring(pids, nodes + more, vnodes).withColumnRenamed("node", "new"), "pid")


def place_locality(centres: DataFrame, nodes: int, seed: int = 3) -> DataFrame:
    """Close centroids (pid, vec) on the same node: clusters of centroids."""
    vs = centres.select(F.col("pid").alias("vec_id"), "vec")
    c = coarse_kmeans(vs, nodes, rounds=6, seed=seed)
    sent = centres.sparkSession.sparkContext.broadcast(c)

    def run(batches):
        for batch in batches:
            x = columns_of(batch)
            node = distance.fast_l2sq(x, sent.value).argmin(axis=1).astype(np.int32) if len(x) else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(node)], ["pid", "node"])

    return vs.mapInArrow(run, "pid long, node int")


def node_load(probes: DataFrame, placement: DataFrame, sizes: DataFrame) -> DataFrame:
    """Queries, partitions and vectors read by node."""
    return probes.join(placement, "pid").join(sizes, "pid").groupBy("node").agg(F.countDistinct("qid").alias("queries"), F.count("*").alias("partitions"), F.sum("n").alias("vectors"))


def imbalance(load: DataFrame) -> DataFrame:
    """Largest load over the mean load."""
    return load.agg((F.max("vectors") / F.avg("vectors")).alias("beta"))


def hottest_share(probes: DataFrame, placement: DataFrame) -> DataFrame:
    """Share of queries that touch the busiest node."""
    per = probes.join(placement, "pid").groupBy("node").agg(F.countDistinct("qid").alias("q"))
    asked = probes.agg(F.countDistinct("qid").alias("all"))
    return per.agg(F.max("q").alias("q")).crossJoin(asked).select((F.col("q") / F.col("all")).alias("hottest_share"))


def slowest_node(probes: DataFrame, placement: DataFrame, sizes: DataFrame) -> DataFrame:
    """Mean over queries of the most vectors that one node must read: what a round waits for."""
    per = probes.join(placement, "pid").join(sizes, "pid").groupBy("qid", "node").agg(F.sum("n").alias("n"))
    return per.groupBy("qid").agg(F.max("n").alias("n")).agg(F.avg("n").alias("waits_for"))


def replicate_hot(placement: DataFrame, reads: DataFrame, nodes: int, copies: int, hot: int) -> DataFrame:
    """pid, node, copy: the `hot` most read partitions get further copies on the next nodes."""
    top = reads.orderBy(F.desc("n"), "pid").limit(hot).select("pid", F.lit(True).alias("is_hot"))
    n = F.when(F.coalesce("is_hot", F.lit(False)), F.lit(copies)).otherwise(F.lit(1))
    spread = placement.join(top, "pid", "left").select("pid", "node", F.explode(F.sequence(F.lit(0), n - 1)).alias("copy"))
    return spread.select("pid", F.pmod(F.col("node") + F.col("copy"), F.lit(nodes)).cast("int").alias("node"), "copy")


def route(probes: DataFrame, copies: DataFrame, down: list[int] = ()) -> DataFrame:
    """qid, pid, node: each probe goes to a healthy copy, queries spread over the copies."""
    up = copies.where(~F.col("node").isin(list(down))) if down else copies
    w = Window.partitionBy("qid", "pid").orderBy(F.pmod(F.col("copy") + F.col("qid"), F.lit(1 << 20)), "node")
    return probes.select("qid", "pid").join(up, "pid").withColumn("n", F.row_number().over(w)).where("n = 1").select("qid", "pid", "node")
