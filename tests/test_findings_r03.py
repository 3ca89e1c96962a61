"""What the review of round 3 found, on small inputs that show it."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.functions import distance
from levelindex.operators import baselines, cluster, exact, granularity, graph, search
from levelindex.operators.build import RootBudget, build_index, footprint, shallower
from levelindex.plans import workloads


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def vectors(spark, x, ids=None):
    ids = range(len(x)) if ids is None else ids
    return scratch.save(spark.createDataFrame([(int(i), [float(c) for c in v]) for i, v in zip(ids, x)], "vec_id long, vec array<double>"), "given")


def asked(vs):
    return vs.select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))


def calls(monkeypatch, where, name):
    """The arguments of each call of a function from now on."""
    seen, f = [], getattr(where, name)
    monkeypatch.setattr(where, name, lambda *a, **b: seen.append(a) or f(*a, **b))
    return seen


@pytest.fixture(scope="module")
def line(spark):
    x = np.random.default_rng(11).integers(0, 60, size=(4200, 4))
    return vectors(spark, x[:4000]), asked(vectors(spark, x[4000:], range(4000, 4200)))


@pytest.mark.parametrize("k", (300, 3000))
def test_nearest_centres_are_those_of_all_pairs(k):
    x = np.random.default_rng(2).integers(0, 40, size=(6000, 5)).astype(float)
    c = np.concatenate([x[:k] + 0.25, x[:3]])
    assert (distance.nearest_centre(x, c) == distance.block("l2sq", x, c).argmin(axis=1)).all()


def test_exact_levels_are_ranked_once_for_all_shallower_indexes(spark, line, monkeypatch):
    base, qs = line
    deepest = build_index(base, RootBudget(vectors=1), density=0.1, levels=4)
    truth = search.level_truth(deepest, qs, 8, 5, base)
    scans = calls(monkeypatch, search, "exact_blocks")
    shared = [rows(search.level_accuracy(shallower(deepest, n), qs, 8, 5, root="exact", truth=truth)) for n in (2, 3, 4)]
    assert not scans
    assert shared == [rows(search.level_accuracy(shallower(deepest, n), qs, 8, 5, root="exact")) for n in (2, 3, 4)]


def test_queries_of_few_numbers_read_the_set_once(spark):
    x = np.random.default_rng(5).integers(0, 30, size=(9000, 3))
    qs, base = asked(vectors(spark, x)), vectors(spark, x[:700])
    assert len(list(exact.query_blocks(qs, beside=10))) == 1
    assert rows(exact.exact_blocks(base, qs, 5)) == rows(exact.exact_blocks(base, qs.where("qid < 4000"), 5).unionByName(exact.exact_blocks(base, qs.where("qid >= 4000"), 5)))


def test_candidates_are_thinned_out_together_as_one_by_one():
    x = np.random.default_rng(7).integers(0, 9, size=(400, 3)).astype(float)
    d = distance.block("l2sq", x[:150], x[150:])
    near = np.argsort(d, axis=1, kind="stable")[:, :60]
    d = np.take_along_axis(d, near, 1)
    assert [c.tolist() for c in graph.prune_all(near + 150, d, x, 12, 1.2, "l2sq")] == [graph.prune(a + 150, b, x, 12, 1.2, "l2sq") for a, b in zip(near, d)]


@pytest.mark.parametrize("spread", (40, 9000))
def test_a_root_beyond_one_process_is_measured(spark, monkeypatch, spread):
    x = np.random.default_rng(8).integers(0, 30, size=(9000, 3))
    x[::2] += spread
    root = vectors(spark, np.concatenate([x, x[:60]]))
    g = graph.build_graph(root, degree=6)
    assert graph.links_held(root, degree=6, block=1000) == len(g.links)
    index = build_index(root, RootBudget(vectors=1), density=0.2, levels=2)
    whole = rows(footprint(index))
    monkeypatch.setattr(graph, "MOST_VERTICES", 100)
    assert rows(footprint(index)) == whole and whole[1][3] == 8 * (index.counts[1] * 4 + len(graph.joined(*linked_root(index))[1]))


def linked_root(index):
    ids, vecs = graph.fetched(index.root(), index.counts[1])
    found, _ = graph.pruned(index.spark, vecs, 24, 1.2, "l2sq")
    lists = found.orderBy("id").toArrow().column("links").combine_chunks()
    return *graph.linked(lists.value_lengths().to_numpy(), lists.flatten().to_numpy(), 24), vecs, graph.closest(vecs.mean(axis=0), vecs)


def test_truth_and_coarse_cells_are_made_once_for_all_densities(spark, line, monkeypatch):
    base, qs = line
    monkeypatch.setattr(workloads, "embedding_set", lambda *a: line)
    monkeypatch.setattr(workloads, "line_set", lambda *a: line)
    coarse, scans = calls(monkeypatch, cluster, "coarse_kmeans"), calls(monkeypatch, exact, "exact_blocks")
    got = {r["density"]: r["misrouted"] for r in workloads.w02_misrouting(spark, "").where("set = 'lineitem'").collect()}
    assert (len(coarse), len(scans)) == (2, 2)
    assert got[0.1] == granularity.misrouted(cluster.partition(base, 0.1), base, qs).first()[0]


@pytest.mark.parametrize("name", ("w13_memory_budgets", "w09_density_combinations"))
def test_one_search_gives_recall_reads_and_latency(spark, line, monkeypatch, name):
    monkeypatch.setattr(workloads, "line_set", lambda *a: line)
    searches, roots, coarse = calls(monkeypatch, search, "descend"), calls(monkeypatch, search, "root_candidates"), calls(monkeypatch, cluster, "coarse_kmeans")
    out = getattr(workloads, name)(spark, "").collect()
    assert len(searches) == len(out) and len(roots) == 4
    if name.startswith("w09"):
        levels = [r["levels"] for r in out[::3]]
        assert len(coarse) == 1 + sum(n - 2 for n in levels)


def test_a_shards_partitions_are_ranked_where_they_are(spark, line):
    base, qs = line
    members = scratch.save(baselines.indexed_shards(baselines.random_shards(base, 3), 0.1), "shards")
    assert rows(members.select("vec_id", "shard")) == rows(baselines.random_shards(base, 3).select("vec_id", "shard"))
    ranked = rows(baselines.shard_probes(members, qs, 7))
    heads = members.where("pid = vec_id").select("vec_id", "vec", "shard")
    assert ranked == rows(baselines.shard_search(heads, qs, 7).select("qid", F.col("vec_id").alias("pid"), "shard", "place"))
    assert rows(baselines.places_of(members, qs, spark.createDataFrame(ranked[::5], "qid long, pid long, shard int, place int"))) == ranked[::5]
    plan = baselines.shard_probes(members, qs, 7)._jdf.queryExecution().optimizedPlan().toString()
    assert "Window" not in plan


def test_a_trees_recall_comes_from_one_ranking_of_its_leaves(spark, line, monkeypatch):
    base, qs = line
    tree = scratch.save(baselines.topdown_tree(base, 60), "tree")
    truth = workloads.truth_of(base, qs, 20)
    leaves = tree.groupBy("leaf").count().agg(F.count("*").alias("n"), F.avg("count").alias("size")).first()
    ks = (1, 5, 20)
    want = workloads.recall_curve(lambda m: (baselines.tree_search(tree, qs, 20, m), float(min(m, leaves["n"]) * leaves["size"] + leaves["n"])), truth, ks, 0.95, min(64, leaves["n"]))
    scans = calls(monkeypatch, baselines, "exact_blocks")
    assert workloads.tree_curve(tree, qs, truth, ks, 0.95, 64) == want and len(want) > 1
    assert len(scans) == 1


def test_densities_are_profiled_side_by_side(spark, line):
    base, qs = line
    shares = (0.5, 0.2, 0.1)
    assert rows(granularity.density_profile(base, qs, shares, at_once=3)) == rows(granularity.density_profile(base, qs, shares))
