"""The experiments, re-expressed on the given tables: which method wins and how each measure moves.

Every workload takes whole tables.  Queries are the rows whose key has a stated remainder.  Recall,
reads, partitions, rounds, bytes, hops, node loads and imbalance are measured.  Latencies are the
measured probe logs under the cost model's assumed hardware: a round lasts as long as the busiest
node needs for the query's partitions.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.operators import baselines, cluster, exact, graph, granularity, placement, search, updates
from levelindex.operators.build import LeveledIndex, RootBudget, build_index, footprint, shallower
from levelindex.plans import cost_model
from levelindex.sources import tables

HW = cost_model.Hardware()


def asked_of(split: tuple[DataFrame, DataFrame]) -> tuple[DataFrame, DataFrame]:
    """The set with its queries written apart, in as few files as they need."""
    base, qs = split
    return base, scratch.save(qs.repartition("qid"), "asked")


def side_by_side(steps: list, at_once: int = 4) -> list:
    """Independent measurements share the cluster: their jobs run side by side, results come in the order of the list."""
    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(lambda step: step(), steps))


def line_set(spark: SparkSession, d: str, part: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """The lineitem vectors; queries leave 7 modulo 500. `part` is for growth curves only: the share of hashes kept."""
    rows = tables.line_features(spark, d).select("vec_id", "vec")
    rows = rows if part >= 1 else rows.where((F.col("vec_id") % 500 == 7) | (F.pmod(F.xxhash64("vec_id"), F.lit(1000)) < round(1000 * part)))
    return asked_of(tables.split_queries(scratch.save(rows, "line"), 500, 7))


def document_set(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """The skewed set: documents with their copies."""
    return asked_of(tables.split_queries(scratch.save(tables.normalised(tables.document_vectors(spark, d, 64)).select("vec_id", "vec"), "docs"), 20, 7))


def embedding_set(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    base, qs = asked_of(tables.split_queries(scratch.save(tables.embeddings(spark, d, "uint8"), "embeddings")))
    return base.select("vec_id", "vec"), qs


def frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([{k: (float(v) if isinstance(v, float) else v) for k, v in r.items()} for r in rows])


def recall_of(found: DataFrame, truth: DataFrame) -> float:
    return found.join(truth.select("qid", "vec_id"), ["qid", "vec_id"], "left_semi").count() / max(truth.count(), 1)


def truth_of(base: DataFrame, qs: DataFrame, k: int) -> DataFrame:
    return scratch.save(exact.exact_blocks(base, qs, k), "truth")


def reads_of(index: LeveledIndex, qs: DataFrame, k: int, m: int, root: str = "exact", start: DataFrame | None = None) -> tuple[DataFrame, list[DataFrame], float]:
    """Result, probes of each level and mean vectors read of a query, the root scan included; `start` as in `descend`."""
    found, log = search.descend(index, qs, k, m, root=root, keep_probes=True, start=start)
    found = scratch.save(found, "found")
    steps = search.trace(index, log, m=m) if log else None
    asked = max(qs.count(), 1)
    read = index.counts[-1] + ((steps.agg(F.sum("vectors_read")).first()[0] or 0) / asked if steps is not None else 0)
    return found, log, float(read)


def smallest_budget(index: LeveledIndex, qs: DataFrame, truth: DataFrame, k: int, target: float, most: int = 256) -> tuple[int, float, list[DataFrame]]:
    """The budget, its recall and its probes."""
    m = max(4, k)
    while True:
        found, log, _ = reads_of(index, qs, k, m)
        got = recall_of(found, truth)
        if got >= target or m >= most:
            return m, got, log
        m *= 2


def w01_sharded_hops(spark, d):
    """Steps and cross-node steps of one graph over five nodes, at two recalls."""
    out = []
    for name, (base, qs) in (("embeddings", embedding_set(spark, d)), ("documents", document_set(spark, d))):
        truth = truth_of(base, qs, 5)
        g = graph.build_graph(base)
        place = scratch.save(placement.place_locality(base.select(F.col("vec_id").alias("pid"), "vec"), 5), "nodes")
        for target in (0.9, 0.95):
            ef = 5
            while True:
                found = scratch.save(graph.graph_search(g, qs, 5, ef), "walk")
                got = recall_of(found, truth)
                if got >= target or ef >= len(g.ids):
                    break
                ef *= 2
            s = graph.hop_stats(graph.hops(found, place)).first()
            out.append({"set": name, "target": target, "ef": ef, "recall": got, "steps": s["steps"], "cross_steps": s["cross_steps"], "p99_cross": float(s["p99_cross"]), "cross_share": s["cross_share"]})
    return frame(spark, out)


def w02_misrouting(spark, d):
    """Queries whose neighbour is in another partition than the nearest centroid's, by density."""
    out = []
    for name, (base, qs) in (("embeddings", embedding_set(spark, d)), ("lineitem", line_set(spark, d))):
        truth, centres = truth_of(base, qs, 1), cluster.coarse_centres(base)
        for share in (0.5, 0.1, 0.02):
            members = scratch.save(cluster.partition(base, share, centres=centres), "members")
            out.append({"set": name, "density": share, "misrouted": granularity.misrouted(members, base, qs, truth).first()[0], "mean_distance": granularity.fidelity(members).first()[0]})
    return frame(spark, out)


def w03_density_sweep(spark, d):
    """Reads and cross-node steps against density at recall 0.9: flat, then steep."""
    base, qs = document_set(spark, d)
    return granularity.density_profile(base, qs, (1.0, 0.5, 0.2, 0.1, 0.05, 0.02, 0.01, 0.001), nodes=5, at_once=3)


def busiest(log: DataFrame, sizes: DataFrame, place: DataFrame, asked: int) -> tuple[float, float]:
    """Vectors that the busiest node reads for one query, and the share of queries that touch the most asked node."""
    load = scratch.save(placement.node_load(log.select("qid", "pid"), place, sizes), "load")
    return float(load.agg(F.max("vectors")).first()[0]) / asked, float(load.agg(F.max("queries")).first()[0]) / asked


def w04_scale_comparison(spark, d, most=64):
    """The leveled index against random and k-means shards with an index inside each shard, at growing size and node count, recall at least 0.9.

    The busiest node's reads bound the rate; `scaling` is a method's rate against its own at five nodes.
    """
    def of_size(nodes: int, part: float) -> dict:
        base, qs = line_set(spark, d, part)
        n, asked = base.count(), qs.count()
        truth = truth_of(base, qs, 5)
        rows = {}
        index = build_index(base, RootBudget(vectors=1), density=0.1, levels=3)
        m, got, log = smallest_budget(index, qs, truth, 5, 0.9, most)
        probes = log[-1]
        sizes = index.packed(0).select("pid", "n")
        load, hottest = busiest(probes, sizes, placement.place_hash(sizes.select("pid"), nodes), asked)
        rows["leveled"] = (got, m, nodes, load, hottest, probes.join(sizes, "pid").agg(F.sum("n")).first()[0] / asked)
        spread = {"random_shards": (baselines.random_shards(base, nodes), None), "kmeans_shards": (None, baselines.kmeans_shards(base, nodes))}
        for name, (rows_of, placed) in spread.items():
            members = scratch.save(baselines.indexed_shards(rows_of if placed is None else placed[0], 0.1), "shards")
            turns = None if placed is None else scratch.save(baselines.chosen_shards(placed, qs, nodes), "turns")
            m, p = baselines.least_probes(members, qs, truth, turns, nodes, (4, 16, most), 0.9)
            found, log = baselines.indexed_search(members, qs, 5, m, None if turns is None else turns.where(F.col("turn") <= p))
            got = recall_of(found, truth)
            sizes = members.groupBy("pid").agg(F.count("*").alias("n"))
            home = members.select("pid", F.col("shard").alias("node")).distinct()
            load, hottest = busiest(log, sizes, home, asked)
            rows[name] = (got, m, p, load, hottest, log.join(sizes, "pid").agg(F.sum("n")).first()[0] / asked)
        return {method: (n, nodes, *row) for method, row in rows.items()}

    measured = side_by_side([partial(of_size, nodes, part) for nodes, part in ((5, 0.125), (10, 0.25), (46, 1.0))])
    out = []
    for rows in measured:
        for method, (n, nodes, recall, m, shards, load, hottest, reads) in rows.items():
            out.append({"method": method, "vectors": n, "nodes": nodes, "recall": recall, "budget": m, "shards": shards, "reads": float(reads), "busiest_reads": load, "hottest_share": hottest, "touched": shards / nodes if method != "leveled" else hottest, "leveled_gain": load / rows["leveled"][5], "scaling": measured[0][method][5] / load})
    return frame(spark, out)


def modelled(index: LeveledIndex, qs: DataFrame, m: int, nodes: int, k: int = 5, log: list[DataFrame] | None = None) -> DataFrame:
    """Per query the microseconds of network, reading and computing: each round waits for the node with most of the query's partitions. `log` are the probes, if the search was made."""
    log = log or search.descend(index, qs, k, m, root="exact", keep_probes=True)[1]
    out = None
    for level, probes in zip(range(index.levels - 2, -1, -1), log):
        sizes = index.packed(level).select("pid", "n")
        per = probes.join(sizes, "pid").groupBy("qid", F.pmod(F.xxhash64("pid"), F.lit(nodes)).alias("node")).agg(F.count("*").alias("p"), F.sum("n").alias("n"))
        part = per.groupBy("qid").agg((F.max("p") * HW.io_us).alias("disk_us"), (F.max("n") * 1e6 / HW.distances_per_core_s).alias("compute_us"), F.lit(HW.rtt_us).alias("network_us"))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("qid").agg(*[F.sum(c).alias(c) for c in ("network_us", "disk_us", "compute_us")]).withColumn("latency_us", F.col("network_us") + F.col("disk_us") + F.col("compute_us") + HW.rtt_us)


def w05_latency_at_peak(spark, d):
    """Mean and tail latency of the measured probes by number of nodes and of levels."""
    base, qs = line_set(spark, d)
    out = None
    deepest = build_index(base, RootBudget(vectors=1), density=0.1, levels=4)
    for levels in (3, 4):
        index = shallower(deepest, levels)
        for nodes in (5, 10, 46):
            per = modelled(index, qs, 64, nodes)
            part = per.agg(F.avg("latency_us").alias("mean_us"), *[F.percentile("latency_us", q).alias(n) for n, q in (("p50_us", 0.5), ("p90_us", 0.9), ("p99_us", 0.99))])
            part = part.select(F.lit(levels).alias("levels"), F.lit(nodes).alias("nodes"), "*")
            out = part if out is None else out.unionByName(part)
    return out


def w06_latency_breakdown(spark, d):
    """Rounds, waits for reads and computing by number of levels, over the measured probes."""
    base, qs = line_set(spark, d)
    out = None
    deepest = build_index(base, RootBudget(vectors=1), density=0.1, levels=4)
    for levels in (2, 3, 4):
        index = shallower(deepest, levels)
        part = modelled(index, qs, 64, 5).agg(*[F.avg(c).alias(c) for c in ("network_us", "disk_us", "compute_us", "latency_us")]).withColumn("levels", F.lit(levels))
        out = part if out is None else out.unionByName(part)
    return out


def w07_extreme_scale(spark, d):
    from levelindex.plans.queries import simulate_scale

    return simulate_scale(spark, d)


def w08_granularity_everywhere(spark, d):
    """Reads by density for each set and metric, for the centroids of two levels, and for samples of one set."""
    line = line_set(spark, d)
    sets = {"lineitem": (*line, "l2sq"), "embeddings": (*embedding_set(spark, d), "l2sq")}
    for name, rows, metric in (("documents", tables.document_vectors(spark, d, 64), "cosine"), ("pages", tables.page_vectors(spark, d), "cosine"), ("conversations", tables.turn_vectors(spark, d), "l2sq"), ("embeddings_ip", tables.normalised(tables.embeddings(spark, d)), "ip")):
        vs = scratch.save((rows if metric == "ip" else tables.normalised(rows)).select("vec_id", "vec"), name)
        sets[name] = (*asked_of(tables.split_queries(vs, 20, 7)), metric)
    index = build_index(line[0], RootBudget(vectors=1), density=0.1, levels=3)
    sets["lineitem_level_1"] = (index.members(1).select("vec_id", "vec"), line[1], "l2sq")
    sets["lineitem_level_2"] = (index.root(), line[1], "l2sq")
    base, qs, _ = sets["documents"]
    for share in (10, 30):
        sets[f"documents_{share}_percent"] = (base.where(F.pmod(F.xxhash64("vec_id"), F.lit(100)) < share), qs, "cosine")
    def profile(name: str) -> DataFrame:
        b, q, metric = sets[name]
        return granularity.density_profile(b.select("vec_id", "vec"), q, (0.5, 0.1, 0.02), metric=metric).withColumn("set", F.lit(name)).withColumn("metric", F.lit(metric))

    out = None
    for part in side_by_side([partial(profile, name) for name in sets]):
        out = part if out is None else out.unionByName(part)
    return out


def w09_density_combinations(spark, d):
    """Three levels with a density product of one hundredth: reads and recall."""
    base, qs = line_set(spark, d)
    truth = truth_of(base, qs, 5)
    n, centres = base.count(), cluster.coarse_centres(base)
    out = []
    for combo in ([0.1, 0.1], [0.08, 0.125], [0.125, 0.08], [0.2, 0.05]):
        index = build_index(base, RootBudget(vectors=max(10, round(n * 0.0125))), density=combo, centres=centres)
        start = root_ranks(index, qs, 32)
        for m in (8, 16, 32):
            found, _, read = reads_of(index, qs, 5, m, start=start)
            out.append({"combination": "x".join(map(str, combo)), "levels": index.levels, "m": m, "recall": recall_of(found, truth), "reads": read})
    return frame(spark, out)


def recall_curve(answers, truth: DataFrame, ks, target: float, most: int) -> list[tuple[int, float, dict]]:
    """(m, reads, recall by k) for growing budgets until every k has the target; one search a budget serves all k."""
    out, m = [], 4
    total = {k: truth.where(F.col("rank") <= k).count() for k in ks}
    while True:
        found, reads = answers(m)
        both = scratch.save(found.select("qid", "vec_id", F.col("rank").alias("place")).join(truth.select("qid", "vec_id", "rank"), ["qid", "vec_id"]), "hits")
        hits = both.agg(*[F.sum(((F.col("place") <= k) & (F.col("rank") <= k)).cast("long")).alias(f"k{k}") for k in ks]).first()
        recall = {k: (hits[f"k{k}"] or 0) / max(total[k], 1) for k in ks}
        out.append((m, reads, recall))
        if min(recall.values()) >= target or m >= most:
            return out
        m *= 4


def tree_curve(tree: DataFrame, qs: DataFrame, truth: DataFrame, ks, target: float, most: int) -> list[tuple[int, float, dict]]:
    """`recall_curve` of a tree's search for all budgets from one ranking of the leaves: of the rows of m leaves the k nearest hold
    a true neighbour of rank k or less exactly if its leaf is one of the m, as what is nearer is as true a neighbour."""
    leaves = tree.groupBy("leaf").count().agg(F.count("*").alias("n"), F.avg("count").alias("size")).first()
    ranked = baselines.near_leaves(tree, qs, leaves["n"]).withColumnRenamed("rank", "turn")
    homes = truth.select("qid", "vec_id", "rank").join(tree.select("vec_id", "leaf"), "vec_id")
    places = scratch.save(homes.join(ranked, ["qid", "leaf"]).groupBy("rank", "turn").agg(F.count("*").alias("n")), "hits").collect()  # at most ranks * leaves rows
    total = {k: truth.where(F.col("rank") <= k).count() for k in ks}
    out, m, most = [], 4, min(most, leaves["n"])
    while True:
        recall = {k: sum(r["n"] for r in places if r["rank"] <= k and r["turn"] <= m) / max(total[k], 1) for k in ks}
        out.append((m, float(min(m, leaves["n"]) * leaves["size"] + leaves["n"]), recall))
        if min(recall.values()) >= target or m >= most:
            return out
        m *= 4


def w10_hierarchy_variants(spark, d, ks=(1, 5, 10, 50, 100), targets=(0.9, 0.95), most=256):
    """Ours, two levels, an extra level and the top-down tree at the same root size, on a plain and a skewed set."""
    sets = {}
    for name, (base, qs) in (("lineitem", line_set(spark, d)), ("documents", document_set(spark, d))):
        sets[name] = (base, qs, truth_of(base, qs, max(ks)))

    def leveled(name: str, shares: list[float]):
        base, qs, truth = sets[name]
        index = build_index(base, RootBudget(vectors=1), density=shares, levels=len(shares) + 1)

        def answers(m):
            found, _, read = reads_of(index, qs, max(ks), m)
            return found, read

        return recall_curve(answers, truth, ks, max(targets), most), index.levels - 1

    def top_down(name: str):
        base, qs, truth = sets[name]
        tree = scratch.save(baselines.topdown_tree(base, max(20, base.count() // 100)), "tree")
        return tree_curve(tree, qs, truth, ks, max(targets), most), 1

    variants = {"leveled": [0.1, 0.1], "two_level": [0.01], "extra_level": [0.5, 0.2, 0.1], "top_down": None}
    cases = [(name, v) for name in sets for v in variants]
    curves = side_by_side([partial(leveled, name, variants[v]) if variants[v] else partial(top_down, name) for name, v in cases])
    out = []
    for (name, v), (curve, rounds) in zip(cases, curves):
        asked = sets[name][1].count()
        for k in ks:
            for target in targets:
                m, read, recall = next((c for c in curve if c[2][k] >= target), curve[-1])
                out.append({"variant": v, "set": name, "queries": asked, "k": k, "target": target, "m": m, "recall": recall[k], "reads": float(read), "rounds": rounds})
    return frame(spark, out)


def w11_level_costs(spark, d):
    """Accuracy of each level at one budget: upper levels find more of their exact neighbours."""
    base, qs = line_set(spark, d)
    out = None
    deepest = build_index(base, RootBudget(vectors=1), density=0.1, levels=5)
    truth = search.level_truth(deepest, qs, 16, 5, base)
    for levels in (2, 3, 4, 5):
        index = shallower(deepest, levels)
        part = search.level_accuracy(index, qs, 16, 5, root="exact", truth=truth).withColumn("levels", F.lit(index.levels))
        out = part if out is None else out.unionByName(part)
    return out


def w12_footprint(spark, d):
    """Vectors by level and the root's share, for two to four levels."""
    base, _ = line_set(spark, d)
    out = None
    deepest = build_index(base, RootBudget(vectors=1), density=0.1, levels=5)
    for levels in (2, 3, 4, 5):
        index = shallower(deepest, levels)
        part = footprint(index).withColumn("levels", F.lit(index.levels))
        out = part if out is None else out.unionByName(part)
    return out


def w13_memory_budgets(spark, d):
    """Four root budgets, each a tenth of the one before, one fixed budget of probes: recall falls little, a round is added each time."""
    base, qs = line_set(spark, d)
    truth = truth_of(base, qs, 10)
    out = []
    deepest = build_index(base, RootBudget(vectors=1), density=0.1, levels=5)
    for levels in (2, 3, 4, 5):
        index = shallower(deepest, levels)
        found, log, read = reads_of(index, qs, 10, 32)
        latency = modelled(index, qs, 32, 5, 10, log).agg(F.avg("latency_us")).first()[0]
        out.append({"root_vectors": index.counts[-1], "levels": index.levels, "recall": recall_of(found, truth), "reads": read, "rounds": index.levels - 1, "latency_us": float(latency)})
    return frame(spark, out)


def root_ranks(index: LeveledIndex, qs: DataFrame, m: int) -> DataFrame:
    """The m nearest root vectors of each query, ranked once for all smaller budgets."""
    return scratch.save(search.rank(search.root_candidates(index, qs, m, "exact"), m), "start")


def w14_near_data(spark, d):
    """Bytes of replies near the data against whole partitions; the rows are the same."""
    base, qs = line_set(spark, d)
    index = build_index(base, RootBudget(vectors=max(10, base.count() // 80)))
    start = root_ranks(index, qs, 32)
    out = []
    for m in (8, 16, 32):
        near, log = search.descend(index, qs, 5, m, "near_data", root="exact", keep_probes=True, start=start)
        raw, _ = search.descend(index, qs, 5, m, "raw_transfer", root="exact", start=start)
        key = ["qid", "rank", "vec_id"]
        differs = near.select(key).exceptAll(raw.select(key)).count()
        sums = {mode: search.trace(index, log, mode, m).agg(F.sum("bytes")).first()[0] for mode in ("near_data", "raw_transfer")}
        out.append({"m": m, "near_bytes": int(sums["near_data"]), "raw_bytes": int(sums["raw_transfer"]), "ratio": sums["raw_transfer"] / sums["near_data"], "rows_that_differ": differs})
    return frame(spark, out)


def w15_placement(spark, d, nodes=5):
    """Hash against cluster placement on one probe log: imbalance, hottest node, what a round waits for."""
    base, qs = line_set(spark, d)
    index = build_index(base, RootBudget(vectors=max(10, base.count() // 80)))
    sizes = index.packed(0).select("pid", "n")
    centres = index.members(0).where("pid = vec_id").select("pid", "vec")
    policies = {"hash": placement.place_hash(centres, nodes), "cluster": scratch.save(placement.place_locality(centres, nodes), "nodes")}
    start = root_ranks(index, qs, 32)
    out = []
    for m in (8, 16, 32):
        probes = search.descend(index, qs, 5, m, root="exact", keep_probes=True, start=start)[1][-1]
        for name, place in policies.items():
            out.append({"m": m, "policy": name, "beta": float(placement.imbalance(placement.node_load(probes, place, sizes)).first()[0]), "hottest_share": float(placement.hottest_share(probes, place).first()[0]), "waits_for": float(placement.slowest_node(probes, place, sizes).first()[0])})
    return frame(spark, out)


def w16_touch_share(spark, d):
    """Share of shards a query touches and the hottest shard's share, from the scale comparison."""
    rows = scratch.save(w04_scale_comparison(spark, d), "scale")
    return rows.select("method", "nodes", F.round("touched", 4).alias("touched"), "hottest_share")


def w17_update_replay(spark, d):
    """Events inserted in order of time into an index that splits and merges as it goes, then a user group's rows deleted; recall after each step."""
    rows = scratch.save(tables.event_vectors(spark, d).select("vec_id", "vec", "user_id"), "events")
    qs = rows.where("vec_id % 100 = 5").select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
    half, rest = rows.approxQuantile("vec_id", [0.5, 0.75], 0.0)
    live = rows.where(F.col("vec_id") <= half)
    index = build_index(live, RootBudget(vectors=1), density=0.1, levels=3)
    out = []

    def note(step: str) -> None:
        sizes = index.packed(0).agg(F.count("*").alias("p"), F.max("n").alias("most"), F.sum("n").alias("n")).first()
        got = recall_of(search.search(index, qs, 5, 32, root="exact"), truth_of(live.select("vec_id", "vec"), qs, 5))
        out.append({"step": step, "vectors": sizes["n"], "partitions": sizes["p"], "largest": sizes["most"], "root": index.counts[-1], "recall": got})

    note("start")
    for name, low, high in (("insert_1", half, rest), ("insert_2", rest, float("inf"))):
        new = rows.where((F.col("vec_id") > low) & (F.col("vec_id") <= high))
        index, live = updates.maintain(index, new.select("vec_id", "vec")), live.unionByName(new)
        note(name)
    dead = "user_id % 10 = 3 and vec_id % 100 != 5"
    index, live = updates.maintain(index, gone=live.where(dead).select("vec_id")), live.where(f"not ({dead})")
    note("delete")
    return frame(spark, out)


def w18_level_table(spark, d):
    from levelindex.plans.queries import level_plan

    return level_plan(spark, d)


QUERIES = {f.__name__: f for f in (w01_sharded_hops, w02_misrouting, w03_density_sweep, w04_scale_comparison, w05_latency_at_peak, w06_latency_breakdown, w07_extreme_scale, w08_granularity_everywhere, w09_density_combinations, w10_hierarchy_variants, w11_level_costs, w12_footprint, w13_memory_budgets, w14_near_data, w15_placement, w16_touch_share, w17_update_replay, w18_level_table)}
