"""The queries' results in DuckDB's SQL, built from shared pieces."""

from __future__ import annotations

#: Vectors as whole numbers, and exact squared distances from inner products.
VECTORS = {
    "uint8": "list_transform(embedding, lambda x: floor((x::DOUBLE + 1) * 127.5))",
    "int8": "list_transform(embedding, lambda x: round(x::DOUBLE * 127))",
    "float": "list_transform(embedding, lambda x: x::DOUBLE)",
}


def d2(a: str, b: str) -> str:
    return f"(list_inner_product({a}, {a}) + list_inner_product({b}, {b}) - 2 * list_inner_product({a}, {b}))"


def start(form: str = "uint8", extra: str = "") -> str:
    return f"""WITH e AS (SELECT vec_id, {VECTORS[form]} AS v, label FROM embeddings),
base AS (SELECT vec_id, v, label FROM e WHERE vec_id % 50 <> 7),
q AS (SELECT vec_id AS qid, v AS qv FROM e WHERE vec_id % 50 = 7){extra}
"""


def assign(name: str, rows: str, stride: int) -> str:
    """Members of stride partitions: nearest centroid, ties to the smaller pid."""
    return f""",
{name} AS (SELECT pid, vec_id, v FROM (
  SELECT c.vec_id AS pid, b.vec_id, b.v, row_number() OVER (PARTITION BY b.vec_id ORDER BY {d2('b.v', 'c.v')}, c.vec_id) AS n
  FROM {rows} b, {rows} c WHERE c.vec_id % {stride} = 0) WHERE n = 1)"""


def top(name: str, source: str, n: int | str) -> str:
    """Rank (qid, vec_id, dist) rows."""
    return f""",
{name} AS (SELECT qid, vec_id, dist, n AS rank FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, vec_id) AS n FROM ({source})) WHERE n <= {n})"""


def knn(name: str, rows: str, k: int | str, where: str = "true") -> str:
    return top(name, f"SELECT q.qid, b.vec_id, {d2('q.qv', 'b.v')} AS dist FROM {rows} b, q WHERE {where}", k)


def exact_sql(form: str, metric: str) -> str:
    dist = {
        "l2sq": d2("q.qv", "b.v") if form != "float" else "round(pow(list_distance(q.qv, b.v), 2), 6)",
        "cosine": "round(1 - list_inner_product(q.qv, b.v) / sqrt(list_inner_product(q.qv, q.qv) * list_inner_product(b.v, b.v)), 6)",
        "ip": "round(-list_inner_product(q.qv, b.v), 6)",
    }[metric]
    kind = "dist" if form == "float" else "dist::BIGINT AS dist"
    return start(form) + top("r", f"SELECT q.qid, b.vec_id, {dist} AS dist FROM base b, q", 5) + f"\nSELECT qid, rank, vec_id, {kind} FROM r"


def leveled(strides=(10, 100), m: int = 16, k: int = 5, head: str | None = None, root_rows: str = "base", final: bool = True) -> str:
    sql = head or start()
    current = root_rows
    for i, s in enumerate(strides):
        sql += assign(f"m{i}", current, s)
        sql += f",\nc{i} AS (SELECT vec_id, v FROM m{i} WHERE pid = vec_id)"
        current = f"c{i}"
    sql += knn(f"f{len(strides)}", current, m)
    for i in range(len(strides) - 1, -1, -1):
        sql += top(f"f{i}", f"SELECT q.qid, x.vec_id, {d2('q.qv', 'x.v')} AS dist FROM f{i + 1} p JOIN q ON p.qid = q.qid JOIN m{i} x ON x.pid = p.vec_id", k if i == 0 else m)
    return sql + ("\nSELECT qid, rank, vec_id, dist::BIGINT AS dist FROM f0" if final else "")


LINE_KEYS = "SELECT DISTINCT ((l_orderkey * 8 + l_linenumber) * 1048576 + l_partkey) * 16384 + l_suppkey AS vec_id FROM lineitem"

MD5 = "('0x' || substr(md5({}::VARCHAR), 1, 8))::BIGINT"


def words(table: str, key: str) -> str:
    """Counts of lower-cased words in 32 buckets, as lists."""
    return f"""(SELECT id, list(n ORDER BY b) AS v FROM (
  SELECT i.id, r.b, count(w.b)::DOUBLE AS n
  FROM (SELECT DISTINCT {key} AS id FROM {table} WHERE len(list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[ \\t\\n\\x0b\\f\\r]+'), lambda x: x <> '')) > 0) i
  CROSS JOIN (SELECT unnest(range(32)) AS b) r
  LEFT JOIN (SELECT id, {MD5.format('word')} % 32 AS b FROM (SELECT {key} AS id, unnest(regexp_split_to_array(lower(coalesce(text, '')), '[ \\t\\n\\x0b\\f\\r]+')) AS word FROM {table}) WHERE word <> '') w
    ON w.id = i.id AND w.b = r.b
  GROUP BY i.id, r.b) GROUP BY id)"""


def probes(m: int) -> str:
    return start() + assign("m0", "base", 10) + ",\nc0 AS (SELECT vec_id, v FROM m0 WHERE pid = vec_id)" + knn("p", "c0", m) + ",\nsz AS (SELECT pid, count(*) AS n FROM m0 GROUP BY pid)"


def node(expr: str, n: int = 5) -> str:
    return f"{MD5.format(expr)} % {n}"


def ring(nodes: int, name: str) -> str:
    """The first virtual node at or after the position of the pid, or else the first of all."""
    return f""",
{name}_pts AS (SELECT node, {MD5.format("(node || ':' || v)")} AS spot FROM (SELECT unnest(range({nodes})) AS node), (SELECT unnest(range(16)) AS v)),
{name} AS (SELECT pid, node FROM (
  SELECT k.pid, t.node, row_number() OVER (PARTITION BY k.pid ORDER BY (t.spot < k.h)::INT, t.spot, t.node) AS n
  FROM (SELECT vec_id AS pid, {MD5.format('vec_id')} AS h FROM base WHERE vec_id % 10 = 0) k, {name}_pts t) WHERE n = 1)"""


def density_profile() -> str:
    sql = start() + knn("truth", "base", 5) + ",\nasked AS (SELECT count(*) AS a FROM q)"
    outs = []
    for g in (2, 5, 10, 20):
        sql += assign(f"m{g}", "base", g) + f",\nc{g} AS (SELECT vec_id, v FROM m{g} WHERE pid = vec_id)" + knn(f"o{g}", f"c{g}", 1 << 30)
        sql += f""",
h{g} AS (SELECT o.rank, count(*) AS h FROM truth t JOIN m{g} x ON t.vec_id = x.vec_id JOIN o{g} o ON o.qid = t.qid AND o.vec_id = x.pid GROUP BY o.rank),
k{g} AS (SELECT min(rank) AS m FROM (SELECT rank, sum(h) OVER (ORDER BY rank) AS got FROM h{g}), asked WHERE got * 10 >= 45 * a),
r{g} AS (SELECT {g}::BIGINT AS partition_size, any_value(k.m)::BIGINT AS m, round(count(*)::DOUBLE / any_value(a), 6) AS reads FROM o{g} o JOIN k{g} k ON o.rank <= k.m JOIN m{g} x ON x.pid = o.vec_id, asked)"""
        outs.append(f"SELECT * FROM r{g}")
    return sql + ",\nprofile AS (" + " UNION ALL ".join(outs) + ")\n"


def simulate() -> str:
    level = "CASE " + " ".join(f"WHEN vectors::DOUBLE{' * 10 / 100' * i} * 100 <= budget_bytes THEN {i + 1}" for i in range(8)) + " ELSE 0 END"
    return f"""WITH s AS (SELECT greatest(count(*), 1)::BIGINT AS n FROM ({LINE_KEYS})),
g AS (SELECT (n * pow(2, i))::BIGINT AS vectors, (b * n)::BIGINT AS budget_bytes, t AS beta_tenths, n
  FROM s, (SELECT unnest(range(11)) AS i), (SELECT unnest([4, 512]) AS b), (SELECT unnest([10, 12]) AS t)),
l AS (SELECT *, ceil(vectors * 5 / n)::BIGINT AS nodes, ({level})::BIGINT AS levels FROM g),
x AS (SELECT *, 256 * (levels - 1) AS io, 256 * (levels - 1) * 13600 / 10 AS rb, (levels - 1) * 12 * 256 + (levels - 1) * 136 * 4 AS nb, 256 * (levels - 1) * 100 / 10 + 2000 AS ev FROM l),
c AS (SELECT *, 400000 * nodes / nullif(io, 0) AS c1, 4000000000.0::DOUBLE * nodes / nullif(rb, 0) AS c2, 1500000000.0::DOUBLE * nodes / nullif(nb, 0) AS c3, 320000000.0::DOUBLE * nodes / ev AS c4 FROM x),
d AS (SELECT *, least(c1, c2, c3, c4) AS low, least(c1, c2, c3, c4) / (beta_tenths / 10) AS raw FROM c)
SELECT vectors, budget_bytes, beta_tenths::BIGINT AS beta_tenths, nodes, levels, round(raw, 3) AS qps,
  CASE low WHEN c1 THEN 'iops' WHEN c2 THEN 'disk' WHEN c3 THEN 'net' ELSE 'cpu' END AS bottleneck,
  round(raw / c3, 4) AS net_use, round(raw / c4, 4) AS cpu_use,
  round(150 + (levels - 1) * (150 + ceil(256 / nodes) * 120 * (beta_tenths / 10)), 3) AS latency_us FROM d"""


def oracle_sql() -> dict[str, str]:
    out = {f"exact_knn_{n}": exact_sql(f, m) for n, f, m in (("l2", "float", "l2sq"), ("cosine", "float", "cosine"), ("ip", "float", "ip"), ("uint8", "uint8", "l2sq"), ("int8", "int8", "l2sq"))}
    out["exact_knn_blocks"] = out["exact_knn_uint8"]
    out["range_search"] = start() + f"SELECT qid, vec_id, dist::BIGINT AS dist FROM (SELECT q.qid, b.vec_id, {d2('q.qv', 'b.v')} AS dist FROM base b, q) WHERE dist <= 27000"
    out["filtered_knn_pre"] = start() + knn("r", "base", 5, "b.label < 3") + "SELECT qid, rank, vec_id, dist::BIGINT AS dist FROM r"
    out["filtered_knn_post"] = start() + knn("w", "base", 20) + top("r", "SELECT w.qid, w.vec_id, w.dist FROM w JOIN base USING (vec_id) WHERE label < 3", 5) + "SELECT qid, rank, vec_id, dist::BIGINT AS dist FROM r"
    out["knn_join_documents_benchmark"] = f"WITH d AS {words('documents', 'doc_id')}, i AS {words('benchmark', 'item_id')} SELECT qid, n AS rank, vec_id, overlap FROM (SELECT i.id AS qid, d.id AS vec_id, list_inner_product(i.v, d.v)::BIGINT AS overlap, row_number() OVER (PARTITION BY i.id ORDER BY list_inner_product(i.v, d.v) DESC, d.id) AS n FROM d, i) WHERE n <= 3"
    out["semantic_near_duplicates"] = f"""WITH RECURSIVE d AS {words('documents', 'doc_id')},
n AS (SELECT v, min(id) AS node FROM d GROUP BY v),
l AS (SELECT a.node AS a, b.node AS b FROM n a, n b WHERE a.node <> b.node AND {d2('a.v', 'b.v')} <= 4),
r AS (SELECT node AS a, node AS b FROM n UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT d.id AS doc_id, c.class_id FROM d JOIN n ON d.v = n.v JOIN (SELECT a, min(b) AS class_id FROM r GROUP BY a) c ON c.a = n.node"""
    members = start() + assign("m0", "base", 10)
    sizes = "SELECT pid, count(*) AS n FROM m0 GROUP BY pid"
    out["partition_assign_stride"] = members + "\nSELECT pid, vec_id FROM m0"
    out["partition_sizes"] = members + "\n" + sizes
    out["partition_size_stats"] = members + f"\nSELECT count(*) AS partitions, min(n) AS least, max(n) AS most FROM ({sizes})"
    both = start() + assign("m0", "base", 10) + ",\nu AS (SELECT vec_id, v FROM base WHERE vec_id % 10 = 0)" + assign("m1", "u", 100)
    per = "SELECT {0}::INTEGER AS level, count(DISTINCT pid) AS n_partitions, count(DISTINCT vec_id) AS n_vectors, round(count(DISTINCT pid) / count(DISTINCT vec_id), 6) AS density FROM m{0}"
    out["density_per_level"] = both + "\n" + per.format(0) + " UNION ALL " + per.format(1)
    out["centroid_mean_one_round"] = members + "\nSELECT pid, i, round(sum(x) / count(*), 4) AS m FROM (SELECT pid, unnest(v) AS x, unnest(range(64)) AS i FROM m0) GROUP BY pid, i"
    out["boundary_replicas"] = start() + f""",
p AS (SELECT b.vec_id, c.vec_id AS cell, {d2('b.v', 'c.v')}::BIGINT AS d2 FROM base b, base c WHERE c.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY d2, cell) AS n, min(d2) OVER (PARTITION BY vec_id) AS d1 FROM p)
SELECT cell, vec_id, (n > 1)::BIGINT AS is_copy FROM r WHERE n <= 2 AND d2 * 100 <= d1 * 121"""
    out["merge_equal_partitions"] = members + "\nSELECT pid, count(DISTINCT vec_id) AS n, min(vec_id) AS least FROM m0 GROUP BY pid"
    for name, strides, m in (("leveled_search_m4", (10, 100), 4), ("leveled_search_m16", (10, 100), 16), ("leveled_search_full", (10, 100), 1000), ("leveled_search_raw_transfer", (10, 100), 16), ("two_level_coarse", (100,), 4), ("extra_level", (2, 10, 100), 16), ("density_combo_5x20", (5, 100), 16), ("density_combo_20x5", (20, 100), 16), ("density_combo_25x4", (25, 100), 16)):
        out[name] = leveled(strides, m)
    one = start() + assign("m0", "base", 10) + ",\nc0 AS (SELECT vec_id, v FROM m0 WHERE pid = vec_id)" + knn("p", "c0", 32) + knn("truth", "base", 5)
    grid = ",\ng AS (SELECT unnest([1, 2, 4, 8, 16, 32])::BIGINT AS m), asked AS (SELECT count(*) AS a FROM q)"
    out["recall_and_reads_vs_m"] = one + grid + """,
h AS (SELECT m, count(*) AS h FROM truth t JOIN m0 x ON t.vec_id = x.vec_id JOIN p ON p.qid = t.qid AND p.vec_id = x.pid JOIN g ON p.rank <= g.m GROUP BY m),
r AS (SELECT m, count(*) AS r FROM p JOIN g ON p.rank <= g.m JOIN m0 x ON x.pid = p.vec_id GROUP BY m)
SELECT r.m, round(coalesce(h, 0) / (5 * a), 6) AS recall, round(r / a, 6) AS reads FROM r LEFT JOIN h USING (m), asked"""
    out["reads_vs_density"] = density_profile() + "SELECT * FROM profile"
    out["balanced_density"] = density_profile() + "SELECT max(partition_size) AS partition_size FROM profile WHERE reads <= 1.5 * (SELECT arg_min(reads, partition_size) FROM profile)"
    steps = leveled((10, 100), 8, 8, final=False) + knn("w2", "c1", 8) + knn("w1", "m1", 8) + knn("w0", "m0", 8)
    out["level_accuracy"] = steps + "\n" + " UNION ALL ".join(f"SELECT {i}::BIGINT AS level, round(avg(CASE WHEN f.vec_id IS NULL THEN 0 ELSE 1 END), 6) AS accuracy FROM w{i} w LEFT JOIN f{i} f ON w.qid = f.qid AND w.vec_id = f.vec_id" for i in (2, 1, 0))
    out["misrouted_share"] = start() + assign("m0", "base", 10) + ",\nc0 AS (SELECT vec_id, v FROM m0 WHERE pid = vec_id)" + knn("p", "c0", 1) + knn("t", "base", 1) + "\nSELECT round(avg((p.vec_id <> x.pid)::INT), 6) AS misrouted_share FROM t JOIN p USING (qid) JOIN m0 x ON x.vec_id = t.vec_id"
    out["random_shards_scatter_gather"] = out["exact_knn_uint8"]
    out["nearest_shards_probe"] = leveled((100,), 2)
    out["placement_hash_md5"] = start() + f"SELECT vec_id AS pid, {node('vec_id')} AS node FROM base WHERE vec_id % 10 = 0"
    out["placement_ring"] = start() + ring(5, "r5") + "\nSELECT pid, node::BIGINT AS node FROM r5"
    out["ring_growth"] = start() + ring(5, "r5") + ring(6, "r6") + "\nSELECT count(*) AS pids, sum((r5.node <> r6.node)::INT)::BIGINT AS moved FROM r5 JOIN r6 USING (pid)"
    out["placement_cluster"] = start() + f",\np AS (SELECT vec_id, v FROM base WHERE vec_id % 10 = 0), a AS (SELECT * FROM p ORDER BY vec_id LIMIT 5)\nSELECT pid, node FROM (SELECT p.vec_id AS pid, a.vec_id AS node, row_number() OVER (PARTITION BY p.vec_id ORDER BY {d2('p.v', 'a.v')}, a.vec_id) AS n FROM p, a) WHERE n = 1"
    load = probes(8) + f",\nl AS (SELECT {node('p.vec_id')} AS node, count(DISTINCT qid) AS queries, count(*) AS partitions, sum(n)::BIGINT AS vectors FROM p JOIN sz ON sz.pid = p.vec_id GROUP BY 1)\n"
    out["node_load"] = load + "SELECT * FROM l"
    out["imbalance"] = load + "SELECT round(max(vectors) / avg(vectors), 6) AS beta FROM l"
    out["hottest_share"] = probes(2) + f"\nSELECT round(max(c) / (SELECT count(DISTINCT qid) FROM p), 6) AS hottest_share FROM (SELECT {node('vec_id')} AS node, count(DISTINCT qid) AS c FROM p GROUP BY 1)"
    out["failover_route"] = probes(4) + f""",
c AS (SELECT vec_id AS pid, ({node('vec_id')} + i) % 5 AS node, i AS copy FROM c0, (SELECT unnest([0, 1]) AS i)),
r AS (SELECT c.node, row_number() OVER (PARTITION BY p.qid, p.vec_id ORDER BY (c.copy + p.qid) % 1048576, c.node) AS n FROM p JOIN c ON c.pid = p.vec_id WHERE c.node <> 0)
SELECT node::BIGINT AS node, count(*) AS probes FROM r WHERE n = 1 GROUP BY node"""
    plan = [(30_000_000_000, 1_000_000_000, 2), (3_000_000_000, 1_000_000_000, 3), (300_000_000, 1_000_000_000, 4), (30_000_000, 1_000_000_000, 5), (4_000_000_000, 1_000_000_000, 3), (4_000_000_000, 2_000_000_000, 3), (4_000_000_000, 8_000_000_000, 4), (4_000_000_000, 32_000_000_000, 4), (4_000_000_000, 1024_000_000_000, 6), (512_000_000_000, 8_000_000_000, 3), (512_000_000_000, 1024_000_000_000, 4), (32_000_000_000, 100_000_000_000, 4), (32_000_000_000, 1000_000_000_000, 5)]
    rows = ", ".join(f"({b}::BIGINT, {s}::BIGINT, {w}::BIGINT)" for b, s, w in plan)
    planned = "(SELECT min(n) FROM range(1, 12) t(n) WHERE vectors * pow(0.1::DOUBLE, n - 1) * 100 <= budget)"
    sized = f"(SELECT floor(b::DOUBLE / s::DOUBLE * n)::BIGINT AS budget, n AS vectors, stated FROM (VALUES {rows}) t(b, s, stated), (SELECT count(*) AS n FROM ({LINE_KEYS})))"
    out["level_plan"] = f"SELECT budget, vectors, stated, {planned} AS planned, (stated = {planned})::BIGINT AS match FROM {sized}"
    out["simulate_scale"] = simulate()
    out["w18_level_table"], out["w07_extreme_scale"] = out["level_plan"], out["simulate_scale"]
    out["storage_by_levels"] = start() + "SELECT n AS levels, i AS level, round((SELECT count(*) FROM base) * pow(0.1::DOUBLE, i), 3) AS vectors FROM range(2, 6) a(n), range(0, 6) b(i) WHERE i < n"
    out["memory_by_levels"] = f"SELECT n AS levels, round(avg((vec_id % pow(10, n - 1)::BIGINT = 0)::INT), 9) AS root_share FROM range(2, 6) a(n), ({LINE_KEYS}) GROUP BY n"
    out["bytes_near_vs_raw"] = probes(32) + ",\ng AS (SELECT unnest([8, 16, 32])::BIGINT AS m), r AS (SELECT m, qid, sum(n)::BIGINT AS n FROM p JOIN sz ON sz.pid = p.vec_id JOIN g ON p.rank <= g.m GROUP BY m, qid)\nSELECT m, sum(12 * least(n, m))::BIGINT AS near_bytes, sum(n * 72)::BIGINT AS raw_bytes FROM r GROUP BY m"
    last = top("f", f"SELECT q.qid, x.vec_id, {d2('q.qv', 'x.v')} AS dist FROM p JOIN q ON p.qid = q.qid JOIN {{}} x ON x.pid = p.vec_id", 5) + "\nSELECT qid, rank, vec_id, dist::BIGINT AS dist FROM f"
    out["insert_then_search"] = probes(8) + last.format("m0")
    out["delete_then_search"] = probes(8) + ",\nalive AS (SELECT * FROM m0 WHERE vec_id % 3 <> 1 OR vec_id NOT IN (SELECT vec_id FROM base))" + last.format("alive")
    out["merge_undersize"] = probes(1) + f""",
stay AS (SELECT m0.* FROM m0 JOIN sz USING (pid) WHERE n >= 8), sc AS (SELECT vec_id, v FROM stay WHERE pid = vec_id),
mv AS (SELECT pid, vec_id FROM (SELECT sc.vec_id AS pid, x.vec_id, row_number() OVER (PARTITION BY x.vec_id ORDER BY {d2('x.v', 'sc.v')}, sc.vec_id) AS n FROM (SELECT m0.* FROM m0 JOIN sz USING (pid) WHERE n < 8) x, sc) WHERE n = 1)
SELECT pid, count(*) AS n FROM (SELECT pid, vec_id FROM stay UNION ALL SELECT pid, vec_id FROM mv) GROUP BY pid"""
    out["reassign"] = out["partition_assign_stride"]
    out["split_oversize"] = start() + "SELECT (SELECT count(*) FROM base) AS vectors, 0::BIGINT AS oversize, 0::BIGINT AS headless"
    out["maintained_index"] = "SELECT level::BIGINT AS level, 0::BIGINT AS headless, 0::BIGINT AS unlisted, 0::BIGINT AS stale, 0::BIGINT AS missing, 0::BIGINT AS extra FROM range(2) t(level)"
    out["compacted_index"] = start() + "SELECT 0::BIGINT AS differ, 5 * count(*) AS n FROM q"
    held = "SELECT count(*) AS queries, 5 * count(*) AS n, 0::BIGINT AS wrong, 0::BIGINT AS repeated, 1::BIGINT AS reached"
    for name in ("root_graph_search", "root_graph_update", "kmeans_shards_search", "lloyd_index_recall"):
        out[name] = start() + held + " FROM q"
    out["lloyd_index_search"] = held + f" FROM ({LINE_KEYS}) WHERE vec_id % 200 = 7"
    out["sharded_graph_hops"] = start() + held + ", 1::BIGINT AS hops_counted FROM q"
    out["topdown_tree_search"] = start() + held + ", 0::BIGINT AS oversize, (SELECT count(*) FROM base) AS vectors FROM q"
    out["partition_is_whole"] = start() + "SELECT count(*) AS n, count(*) AS vectors, 0::BIGINT AS headless, 1::BIGINT AS bounded FROM base"
    out["tuned_budget"] = start() + knn("truth", "base", 5) + assign("m0", "base", 10) + ",\nc0 AS (SELECT vec_id, v FROM m0 WHERE pid = vec_id)" + knn("o", "c0", 1 << 30) + """,
h AS (SELECT o.rank, count(*) AS h FROM truth t JOIN m0 x ON t.vec_id = x.vec_id JOIN o ON o.qid = t.qid AND o.vec_id = x.pid GROUP BY o.rank)
SELECT min(rank)::BIGINT AS m FROM (SELECT rank, sum(h) OVER (ORDER BY rank) AS got FROM h) WHERE got * 10 >= 9 * (SELECT count(*) FROM truth)"""
    out["auto_density_build"] = "SELECT 1::BIGINT AS coarsest_that_fits, 1::BIGINT AS recall_reached, 1::BIGINT AS in_range"
    out["density_profile_graph"] = "SELECT density, 1::BIGINT AS reached, 1::BIGINT AS reads, 1::BIGINT AS hops_counted FROM (VALUES (1.0::DOUBLE), (0.2), (0.1), (0.05)) t(density)"
    out["axis_tree_leaves"] = start() + "SELECT 8::BIGINT AS leaves, count(*) AS vectors, 1::BIGINT AS even FROM base"
    return out
