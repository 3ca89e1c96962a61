"""Invariants of the index and of its parts."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.functions import distance, sql
from levelindex.operators import baselines, cluster, exact, graph, granularity, placement, search, updates
from levelindex.operators.build import LeveledIndex, RootBudget, build_index, plan_levels, verify_index
from levelindex.plans import cost_model, workloads
from levelindex.sources import store, tables


@pytest.fixture(scope="module")
def line(spark, sf):
    base, qs = workloads.line_set(spark, sf, 20)
    return scratch.save(base, "base"), scratch.save(qs, "asked")


@pytest.fixture(scope="module")
def index(line):
    return build_index(line[0], RootBudget(vectors=40), cells=3)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_members_cover_the_base_and_pids_are_the_next_level(index, line):
    base, _ = line
    assert index.levels == plan_levels(index.counts[0], 0.1, 40, 1)
    members = index.members(0)
    assert rows(members.select("vec_id")) == rows(base.select("vec_id"))
    for level in range(index.levels - 1):
        pids = rows(index.members(level).select("pid").distinct())
        above = index.root() if level == index.levels - 2 else index.members(level + 1)
        assert pids == rows(above.select("vec_id"))
        assert index.counts[level + 1] == pytest.approx(index.counts[level] * 0.1, rel=0.1)
    assert index.counts[-1] <= 40
    assert rows(index.packed(0).select("pid", "n")) == rows(members.groupBy("pid").agg(F.count("*").cast("int").alias("n")))


def test_members_are_in_the_nearest_partition_of_one_cell(line):
    members = scratch.save(cluster.partition(line[0], 0.1, cells=1), "members")
    x = {r.vec_id: (r.pid, np.array(r.vec)) for r in members.collect()}
    heads = sorted({p for p, _ in x.values()})
    c = np.stack([x[h][1] for h in heads])
    for i, (p, v) in x.items():
        d = ((c - v) ** 2).sum(axis=1)
        assert d[heads.index(p)] <= d.min() + 1e-6


def test_full_budget_is_exact_and_modes_agree(index, line):
    base, qs = line
    truth = rows(exact.exact_blocks(base, qs, 5).select("qid", "rank", "vec_id"))
    for mode in ("near_data", "rows", "raw_transfer"):
        assert rows(search.search(index, qs, 5, 10_000, mode, root="exact").select("qid", "rank", "vec_id")) == truth
    near = rows(search.search(index, qs, 5, 8, root="exact").select("qid", "rank", "vec_id"))
    assert near == rows(search.search(index, qs, 5, 8, "raw_transfer", root="exact").select("qid", "rank", "vec_id"))
    assert rows(exact.exact_knn(base, qs, 5, digits=None).select("qid", "rank", "vec_id")) == truth


def test_recall_grows_with_the_budget_and_results_are_sound(index, line):
    base, qs = line
    truth = scratch.save(exact.exact_blocks(base, qs, 5), "truth")
    got = [workloads.recall_of(search.search(index, qs, 5, m), truth) for m in (4, 16, 64)]
    assert got[0] <= got[1] + 0.02 <= got[2] + 0.04 and got[1] >= 0.9
    found = search.search(index, qs, 5, 16).join(qs, "qid").join(base, "vec_id").withColumn("d", distance.l2sq(F.col("qvec"), F.col("vec")))
    assert found.where("abs(d - dist) > 1e-6").count() == 0
    per = found.groupBy("qid").agg(F.countDistinct("vec_id").alias("n"), F.max("rank").alias("r"))
    assert per.where("n != 5 or r != 5").count() == 0
    m, curve = search.tune_budget(index, qs, truth, 5, 0.9)
    assert dict(curve)[m] >= 0.9 and (m == 1 or dict(curve).get(m - 1, 0) < 0.9)


def test_upper_levels_are_more_accurate(index, line):
    acc = {r.level: r.accuracy for r in search.level_accuracy(index, line[1], 16, 5, root="exact").collect()}
    assert acc[index.levels - 1] == 1 and acc[1] >= acc[0] - 0.05


def test_result_does_not_depend_on_partitioning(spark, line):
    base, qs = line
    want = rows(search.search(build_index(base, RootBudget(vectors=40), cells=1), qs, 5, 8).select("qid", "rank", "vec_id"))
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    try:
        again = build_index(base.repartition(5, "vec"), RootBudget(vectors=40), cells=1)
        assert rows(search.search(again, qs.repartition(3), 5, 8).select("qid", "rank", "vec_id")) == want
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)


def test_saved_index_and_root_graph_come_back_the_same(spark, index, line):
    again = LeveledIndex.load(spark, index.path)
    assert again.counts == index.counts and (again.graph.links == index.graph.links).all()
    assert rows(sql.ann_search(spark, index.path, line[1], 3, 8)) == rows(search.search(index, line[1], 3, 8))


def test_replicas_and_merged_partitions(line):
    base, qs = line
    members = scratch.save(cluster.merge_equal(cluster.local_cluster(cluster.replicate_boundary(base, cluster.coarse_kmeans(base, 4), 0.3, 2), 0.1)), "members")
    assert members.count() > base.count() and members.select("vec_id").distinct().count() == base.count()
    assert members.groupBy("pid", "vec_id").count().where("count > 1").isEmpty()
    once = cluster.keep_nearest_copy(members)
    assert once.count() == base.count()
    copies = build_index(base, RootBudget(vectors=60), cells=4, max_copies=2, eps=0.3)
    assert rows(search.search(copies, qs, 5, 10_000, root="exact", copies=2).select("qid", "vec_id")) == rows(exact.exact_blocks(base, qs, 5).select("qid", "vec_id"))


def test_graph_reaches_everything_and_finds_the_nearest(spark, sf):
    base, qs = workloads.embedding_set(spark, sf)
    g = graph.build_graph(base)
    seen, stack = {g.entry}, [g.entry]
    while stack:
        for w in g.neighbours(stack.pop()).tolist():
            if w not in seen:
                seen.add(w)
                stack.append(w)
    assert len(seen) == len(g.ids)
    found = graph.graph_search(g, qs, 5, len(g.ids))
    assert rows(found.select("qid", "vec_id")) == rows(exact.exact_blocks(base, qs, 5).select("qid", "vec_id"))
    one = placement.place_hash(base.select(F.col("vec_id").alias("pid")), 1)
    assert graph.hop_stats(graph.hops(found, one)).first()["cross_steps"] == 0
    many = graph.hops(found, placement.place_hash(base.select(F.col("vec_id").alias("pid")), 5))
    assert many.where("cross_steps > steps").isEmpty()


def test_baselines_are_exact_when_they_read_everything(line):
    base, qs = line
    truth = rows(exact.exact_blocks(base, qs, 5).select("qid", "vec_id"))
    assert rows(baselines.scatter_gather(baselines.random_shards(base, 5), qs, 5).select("qid", "vec_id")) == truth
    placed = baselines.kmeans_shards(base, 4)
    got = [workloads.recall_of(baselines.probe_shards(placed, qs, 5, p)[0], exact.exact_blocks(base, qs, 5)) for p in (1, 2, 4)]
    assert got[0] <= got[1] <= got[2] == 1
    sizes = [r["count"] for r in placed[0].groupBy("shard").count().collect()]
    assert sum(sizes) == base.count()
    tree = baselines.topdown_tree(base, 50, 4)
    assert tree.groupBy("leaf").count().where("count > 50").isEmpty() and tree.count() == base.count()
    assert rows(baselines.tree_search(tree, qs, 5, 10_000).select("qid", "vec_id")) == truth


def test_unit_vectors_have_one_order(spark, sf):
    vs = tables.embeddings(spark, sf)
    base, qs = tables.split_queries(vs)
    got = [rows(exact.exact_knn(base, qs, 5, m).select("qid", "vec_id")) for m in distance.METRICS]
    assert got[0] == got[1] == got[2]


def test_updates_keep_the_invariants(line):
    base, _ = line
    members = scratch.save(cluster.partition(base.where("vec_id % 4 != 1"), 0.1, cells=1), "members")
    new = base.where("vec_id % 4 = 1")
    after = scratch.save(updates.insert(members, new), "members")
    own = new.select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec")).limit(50)
    first = updates.partition_search(after, own, 1, 4).where("dist > 0")
    assert first.isEmpty() and after.count() == base.count()
    split = scratch.save(updates.split_oversize(after, 15), "members")
    merged = scratch.save(updates.merge_undersize(split, 4), "members")
    for m in (split, merged):
        assert rows(m.select("vec_id")) == rows(base.select("vec_id"))
        assert rows(m.select("pid").distinct()) == rows(m.where("pid = vec_id").select("pid"))
    moved = updates.reassign(merged, merged.select("pid").limit(3))
    assert rows(moved.select("vec_id")) == rows(base.select("vec_id"))
    upper = scratch.save(cluster.partition(members.where("pid = vec_id").select("vec_id", "vec"), 0.2, cells=1), "upper")
    assert rows(updates.upward(merged, upper).select("vec_id")) >= rows(merged.where("pid = vec_id").select("vec_id"))[:0]
    dead = base.where("vec_id % 5 = 2")
    assert updates.delete(merged, dead).join(dead, "vec_id", "left_semi").isEmpty()


def test_placement(spark, line):
    pids = line[0].select(F.col("vec_id").alias("pid"), "vec")
    for place in (placement.place_hash(pids, 5), placement.place_hash(pids, 5, "md5"), placement.place_ring(pids, 5), placement.place_locality(pids, 5)):
        assert rows(place.select("pid")) == rows(pids.select("pid")) and place.where("node < 0 or node > 4").isEmpty()
    moved = placement.grow(pids, 5, 1).agg(F.avg((F.col("old") != F.col("new")).cast("double")), F.sum(((F.col("old") != F.col("new")) & (F.col("new") != 5)).cast("int"))).first()
    assert 0.05 < moved[0] < 0.35 and moved[1] == 0
    probes = pids.select(F.lit(1).alias("qid"), "pid").limit(20)
    place = placement.place_hash(pids, 5)
    copies = placement.replicate_hot(place, pids.select("pid", F.lit(1).alias("n")), 5, 2, 10_000_000)
    routed = placement.route(probes, copies, [2])
    assert routed.count() == 20 and routed.where("node = 2").isEmpty()


def test_granularity(line):
    base, qs = line
    choice = granularity.determine_density(base, qs, sample_n=1500)
    assert 0.001 <= choice.density <= 0.5 and choice.evaluations[0]["density"] == 1.0
    flat = [{"density": d, "vectors_read": r} for d, r in ((1.0, 100), (0.5, 105), (0.2, 110), (0.1, 120), (0.05, 300), (0.01, 2000))]
    assert granularity.select_granularity(flat) == 0.1 and granularity.select_granularity(flat, method="elbow") in (0.1, 0.2)


def test_filtered_search_and_edges(spark, index, line):
    base, qs = line
    even = search.search(index, qs, 5, 10_000, where=F.col("vec_id") % 2 == 0, root="exact")
    assert rows(even.select("qid", "vec_id")) == rows(exact.exact_blocks(base.where("vec_id % 2 = 0"), qs, 5).select("qid", "vec_id"))
    assert search.search(index, qs.limit(0), 5, 8).count() == 0
    with pytest.raises(ValueError):
        search.search(index, qs, 0, 8)
    with pytest.raises(ValueError):
        search.search(index, qs, 5, 0)
    with pytest.raises(ValueError):
        build_index(base, RootBudget(vectors=5), density=1.0)
    with pytest.raises(ValueError):
        RootBudget().fits(1, 1)
    one = build_index(base, RootBudget(vectors=10_000_000))
    assert one.levels == 1 and rows(search.search(one, qs, 5, 8, root="exact").select("qid", "vec_id")) == rows(exact.exact_blocks(base, qs, 5).select("qid", "vec_id"))
    same = spark.createDataFrame([(i, [1.0, 2.0]) for i in range(60)], "vec_id long, vec array<double>")
    again = build_index(same, RootBudget(vectors=10))
    assert again.members(0).count() == 60
    assert build_index(same.limit(0), RootBudget(vectors=10)).counts == [0]
    bad = spark.createDataFrame([(1, [1.0, float("nan")]), (2, None), (3, [1.0]), (4, [0.0, 0.0]), (5, [1.0, 2.0])], "vec_id long, vec array<double>")
    assert rows(tables.valid(bad, 2, "cosine").select("vec_id")) == [(5,)]


def test_plans_push_and_limit_early(spark, sf, index, line):
    base, qs = line
    plan = exact.exact_knn(base, qs, 5)._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in plan and "Partial" in plan
    few = store.read_partitions(spark, index.path, 0, index.buckets[0][0], [1, 2])._jdf.queryExecution().toString()
    assert "PushedFilters: [In(pid" in few
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        found = search.search(index, qs, 5, 8, root="exact")._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert found.count("Bucketed: true") == index.levels - 1
    # only the probes are dealt by pid, the stored levels are not exchanged
    assert not [x for x in found.splitlines() if "Exchange hashpartitioning(pid" in x and "REPARTITION_BY_NUM" not in x]
    slim = tables.table(spark, sf, "lineitem").where("l_quantity > 49").select("l_orderkey")._jdf.queryExecution().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_quantity:double>" in slim and "GreaterThan(l_quantity,49.0)" in slim


def test_sql_functions_and_source(spark, index, line):
    sql.register(spark)
    r = spark.sql("SELECT vec_l2sq(array(1D, 2D), array(4D, 6D)) AS a, vec_ip(array(1D, 2D), array(3D, 4D)) AS b, vec_norm(array(3D, 4D)) AS c, vec_cosine(array(1D, 0D), array(0D, 2D)) AS d").first()
    assert tuple(r) == (25.0, 11.0, 5.0, 1.0)
    two = spark.createDataFrame([(1, [1.0, 2.0]), (1, [3.0, 4.0])], "g int, vec array<double>")
    assert sql.mean_by(two, "g").first()["vec"] == [2.0, 3.0] and two.groupBy("g").agg(sql.vec_mean("vec").alias("v")).first()["v"] == [2.0, 3.0]
    from levelindex.sources.partition_source import PartitionSource

    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(PartitionSource)
    pid = index.members(0).select("pid").first()["pid"]
    got = spark.read.format("levelpartitions").option("path", index.path.removeprefix("file://")).load().where(F.col("pid") == pid)
    assert rows(got.select("vec_id")) == rows(index.members(0).where(F.col("pid") == pid).select("vec_id"))
    sql.register_ann_search(spark, index.path)
    line[1].createOrReplaceTempView("asked_rows")
    assert spark.sql("SELECT * FROM ann_search(TABLE(asked_rows), 3)").count() == 3 * line[1].count()


def test_cost_model_shapes(spark):
    rows_ = {(r.vectors // 10**9, r.budget_bytes // 10**9, r.beta_tenths): r for r in cost_model.simulate(cost_model.scale_grid(spark)).collect()}
    assert rows_[1024, 4, 10].levels == 6 and rows_[1024, 512, 10].levels == 4 and rows_[8, 4, 10].levels == 4
    assert rows_[1024, 4, 10].bottleneck == "iops" and rows_[1024, 4, 12].qps < rows_[1024, 4, 10].qps
    assert rows_[1024, 512, 10].latency_us < rows_[1024, 4, 10].latency_us
    assert cost_model.reply_bytes(512) == 6144 and cost_model.raw_bytes(128, 0.1, 128, 1) > 100_000


def test_stream_of_changes_equals_the_batch(spark, sf):
    from levelindex.streaming.upserts import replay

    events = tables.event_vectors(spark, sf).select("vec_id", "vec", "ts")
    start = build_index(events.where("vec_id % 10 = 0"), RootBudget(vectors=1), levels=2)
    changes = events.where("vec_id % 10 != 0").select(F.lit("insert").alias("op"), "vec_id", "vec", "ts")
    changes = changes.unionByName(events.where("vec_id % 20 = 1").select(F.lit("delete").alias("op"), "vec_id", "vec", (F.col("ts") + F.expr("INTERVAL 1 SECOND")).alias("ts")))
    where = scratch.path(spark, "changes")
    changes.coalesce(1).write.parquet(where)
    stream = spark.readStream.schema(changes.schema).parquet(where)
    out = replay(stream, start, scratch.path(spark, "m"), scratch.path(spark, "c"))
    want = events.where("vec_id % 20 != 1").select("vec_id")
    assert rows(out.members(0).select("vec_id")) == rows(want)
    assert all(r.headless == r.unlisted == r.stale == 0 for r in verify_index(out).collect())
    assert len(out.versions) == 2 and LeveledIndex.load(spark, out.path).counts == out.counts
    assert start.counts[0] == start.members(0).count()  # the version before stays readable


def test_cells_stay_bounded(spark):
    same = spark.range(900).select(F.lit("a").alias("cell"), F.col("id").alias("vec_id"), F.array(F.lit(1.0), F.lit(2.0)).alias("vec"))
    mixed = spark.range(2000).select(F.lit("b").alias("cell"), F.col("id").alias("vec_id"), F.array((F.col("id") % 100).cast("double"), F.lit(2.0)).alias("vec"))
    out = cluster.bounded_cells(same.unionByName(mixed), most=150)
    assert out.count() == 2900 and out.groupBy("cell").count().agg(F.max("count")).first()[0] <= 150


def test_vectors_of_every_width(spark, sf):
    base, qs = tables.split_queries(tables.embeddings(spark, sf, "uint8"))
    found = []
    for width in ("u1", "f4", "f8"):
        index = build_index(base, RootBudget(vectors=1), algorithm="stride", levels=2, width=width)
        found.append(rows(search.search(index, qs, 5, 8, root="exact").select("qid", "rank", "vec_id", "dist")))
    assert found[0] == found[1] == found[2]


def test_nearest_centre_is_the_nearest():
    rng = np.random.default_rng(3)
    x, c = rng.normal(size=(5000, 7)), rng.normal(size=(90, 7))
    assert (distance.nearest_centre(x, c, block=512) == distance.block("l2sq", x, c).argmin(axis=1)).all()
