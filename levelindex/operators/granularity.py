"""How fine to partition: read cost by density, and the coarsest density before it climbs."""

from __future__ import annotations

import math
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.functions import distance
from levelindex.operators import cluster
from levelindex.operators.exact import exact_blocks
from levelindex.operators.graph import build_graph, graph_search, hop_stats, hops
from levelindex.operators.placement import place_locality


@dataclass
class GranularityChoice:
    density: float
    evaluations: list[dict]


def evaluate(vs: DataFrame, qs: DataFrame, truth: DataFrame, share: float, k: int, target: float, metric: str = "l2sq", nodes: int = 0, algorithm: str = "lloyd") -> dict:
    """Cluster at one density and find the least budget for the target: visits in the centroids' graph plus members read."""
    spark = vs.sparkSession
    members = scratch.save(vs.select(F.col("vec_id").alias("pid"), "vec_id", "vec") if share >= 1 else cluster.partition(vs, share, algorithm=algorithm), "profile")
    centres = members.where("pid = vec_id").select("vec_id", "vec")
    graph = build_graph(centres, metric=metric)
    sizes = members.groupBy("pid").agg(F.count("*").alias("n"))
    homes = members.select("vec_id", "pid").dropDuplicates(["vec_id"])
    want = scratch.save(truth.select("qid", "vec_id").join(homes, "vec_id").select("qid", "pid"), "want")
    asked, total = qs.count(), truth.count()
    m = max(k if share >= 1 else 1, first_budget(graph, qs, want, total, k, target))
    while True:
        found = scratch.save(graph_search(graph, qs, m, ef=max(m, k)), "ranked")
        hit = want.join(found.select("qid", F.col("vec_id").alias("pid")), ["qid", "pid"], "left_semi").count()
        recall = hit / max(total, 1)
        if recall >= target or m >= len(graph.ids):
            cost = found.where("rank = 1").agg(F.avg("steps").alias("s"), F.avg("visits").alias("v")).first()
            read = found.select("qid", F.col("vec_id").alias("pid")).join(sizes, "pid").agg(F.sum("n").alias("n")).first()["n"] or 0
            result = {"density": share, "budget": m, "recall": recall, "visits": float(cost["v"] or 0), "steps": float(cost["s"] or 0), "members_read": 0.0 if share >= 1 else read / max(asked, 1)}
            result["vectors_read"] = result["visits"] + result["members_read"]
            if nodes:
                place = place_locality(centres.withColumnRenamed("vec_id", "pid"), nodes)
                result["cross_steps"] = float(hop_stats(hops(found, place)).first()["cross_steps"] or 0)
            graph.release()
            return result
        m = min(len(graph.ids), max(m + 1, math.ceil(m * 1.4)))


def first_budget(graph, qs: DataFrame, want: DataFrame, total: int, k: int, target: float) -> int:
    """Where the search for the least budget starts: the ranks of one wide walk tell what each smaller budget would find at best."""
    wide = 64
    while True:
        wide = min(wide, len(graph.ids))
        ranked = graph_search(graph, qs, wide, ef=max(wide, k)).select("qid", F.col("vec_id").alias("pid"), "rank")
        hits = {r["rank"]: r["n"] for r in want.join(ranked, ["qid", "pid"]).groupBy("rank").agg(F.count("*").alias("n")).collect()}  # at most `wide` rows
        run = 0
        for place in range(1, wide + 1):
            run += hits.get(place, 0)
            if run >= target * total:
                return place
        if wide >= len(graph.ids):
            return max(1, wide)
        wide *= 4


def density_profile(vs: DataFrame, qs: DataFrame, densities=(1.0, 0.5, 0.2, 0.1, 0.05, 0.02, 0.01), k: int = 5, target: float = 0.9, metric: str = "l2sq", nodes: int = 0, algorithm: str = "lloyd", at_once: int = 1) -> DataFrame:
    """One row for each density. The grid is a handful of numbers; each step is a distributed build of many small jobs, and `at_once` steps share the cluster."""
    truth = scratch.save(exact_blocks(vs, qs, k, metric), "truth")
    with ThreadPoolExecutor(at_once) as pool:
        rows = list(pool.map(lambda d: evaluate(vs, qs, truth, d, k, target, metric, nodes, algorithm), densities))
    return vs.sparkSession.createDataFrame(rows)


def select_granularity(profile: list[dict], tolerance: float = 1.5, method: str = "ratio") -> float:
    """The coarsest density whose reads stay within `tolerance` of the finest's ('ratio'), or the knee of the log-log curve ('elbow')."""
    rows = sorted(profile, key=lambda r: -r["density"])
    if method == "ratio":
        limit = tolerance * rows[0]["vectors_read"]
        return min(r["density"] for r in rows if r["vectors_read"] <= limit)
    if method != "elbow":
        raise ValueError("the method is 'ratio' or 'elbow'")
    x, y = np.log([1 / r["density"] for r in rows]), np.log([max(r["vectors_read"], 1e-9) for r in rows])
    if len(rows) < 3:
        return rows[-1]["density"]
    chord = y[0] + (y[-1] - y[0]) * (x - x[0]) / (x[-1] - x[0])
    return rows[int(np.argmax(chord - y))]["density"]


def determine_density(vs: DataFrame, qs: DataFrame | None = None, sample_n: int = 1_000_000, k: int = 5, target: float = 0.9, g_max: int = 1000, tolerance: float = 1.5, metric: str = "l2sq", asked: int = 100) -> GranularityChoice:
    """Profile a hash sample: the finest first, then halve the interval of partition sizes until reads jump."""
    sample = scratch.save(cluster.hash_sample(vs, sample_n, 17), "sample")
    if qs is None:
        picked = scratch.save(cluster.hash_sample(sample, asked, 23), "asked")
        qs = picked.select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
        sample = sample.join(picked.select("vec_id"), "vec_id", "left_anti")
    truth = scratch.save(exact_blocks(sample, qs, k, metric), "truth")
    rows = [evaluate(sample, qs, truth, 1.0, k, target, metric)]
    low, high = 1, max(2, min(g_max, sample.count() // 4))
    while high - low > max(1, low // 4):
        g = round(math.sqrt(low * high))
        if g in (low, high):
            break
        rows.append(evaluate(sample, qs, truth, 1 / g, k, target, metric))
        low, high = (g, high) if rows[-1]["vectors_read"] <= tolerance * rows[0]["vectors_read"] else (low, g)
    fits = [r["density"] for r in rows[1:] if r["vectors_read"] <= tolerance * rows[0]["vectors_read"]]
    return GranularityChoice(min(fits) if fits else 0.5, rows)


def misrouted(members: DataFrame, vs: DataFrame, qs: DataFrame, truth: DataFrame | None = None) -> DataFrame:
    """Share of queries whose true nearest vector (`truth`: qid, vec_id, if known) is not in the partition of the nearest centroid."""
    centres = members.where("pid = vec_id").select(F.col("pid").alias("vec_id"), "vec")
    near = exact_blocks(centres, qs, 1).select("qid", F.col("vec_id").alias("pid"))
    truth = (exact_blocks(vs, qs, 1) if truth is None else truth).select("qid", "vec_id")
    home = members.select("vec_id", F.col("pid").alias("home")).dropDuplicates(["vec_id"])
    return truth.join(near, "qid").join(home, "vec_id").agg(F.avg((F.col("pid") != F.col("home")).cast("double")).alias("misrouted_share"))


def fidelity(members: DataFrame) -> DataFrame:
    centre = members.where("pid = vec_id").select("pid", F.col("vec").alias("c"))
    return members.join(centre, "pid").agg(F.avg(F.sqrt(distance.l2sq(F.col("vec"), F.col("c")))).alias("mean_distance"))
