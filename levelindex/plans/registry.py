"""Names of the engine's queries, with their SQL where SQL can say the same."""

from __future__ import annotations

from levelindex.operators import relational
from levelindex.plans import oracle
from levelindex.plans import queries as q
from levelindex.plans import workloads
from levelindex.streaming import queries as streams


def queries() -> dict:
    out = {
        "exact_knn_l2": q.exact_knn("float", "l2sq"),
        "exact_knn_cosine": q.exact_knn("float", "cosine"),
        "exact_knn_ip": q.exact_knn("float", "ip"),
        "exact_knn_uint8": q.exact_knn("uint8", "l2sq"),
        "exact_knn_int8": q.exact_knn("int8", "l2sq"),
        "filtered_knn_pre": q.filtered_knn("pre"),
        "filtered_knn_post": q.filtered_knn("post"),
        "leveled_search_m4": q.leveled_search(4),
        "leveled_search_m16": q.leveled_search(16),
        "leveled_search_full": q.leveled_search(1000),
        "leveled_search_raw_transfer": q.leveled_search(16, raw=True),
        "two_level_coarse": q.leveled_search(4, (100,)),
        "extra_level": q.leveled_search(16, (2, 10, 100)),
        "density_combo_5x20": q.leveled_search(16, (5, 100)),
        "density_combo_20x5": q.leveled_search(16, (20, 100)),
        "density_combo_25x4": q.leveled_search(16, (25, 100)),
        "reads_vs_density": q.reads_vs_density_frame,
    }
    plain = (q.exact_knn_blocks, q.range_search, q.knn_join_documents_benchmark, q.semantic_near_duplicates, q.partition_assign_stride, q.partition_sizes, q.partition_size_stats, q.density_per_level, q.centroid_mean_one_round, q.boundary_replicas, q.merge_equal_partitions, q.recall_and_reads_vs_m, q.balanced_density, q.level_accuracy, q.misrouted_share, q.random_shards_scatter_gather, q.nearest_shards_probe, q.placement_hash_md5, q.placement_ring, q.ring_growth, q.placement_cluster, q.node_load, q.imbalance, q.hottest_share, q.failover_route, q.level_plan, q.simulate_scale, q.storage_by_levels, q.memory_by_levels, q.bytes_near_vs_raw, q.insert_then_search, q.delete_then_search, q.merge_undersize, q.split_oversize, q.reassign, q.maintained_index, q.compacted_index, q.root_graph_update, q.lloyd_index_search, q.lloyd_index_recall, q.tuned_budget, q.partition_is_whole, q.root_graph_search, q.sharded_graph_hops, q.kmeans_shards_search, q.topdown_tree_search, q.axis_tree_leaves, q.auto_density_build, q.density_profile_graph)
    return out | {f.__name__: f for f in plain} | relational.QUERIES | streams.QUERIES | workloads.QUERIES


def oracle_sql() -> dict:
    return oracle.oracle_sql() | relational.ORACLE | streams.ORACLE
