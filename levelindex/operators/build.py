"""The leveled index: partition, take the centroids as the next set, repeat until the root fits."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.operators import cluster
from levelindex.operators.graph import Graph, build_graph, links_held
from levelindex.sources import store


@dataclass(frozen=True)
class RootBudget:
    """How much of the top set one server's memory takes: a number of vectors, or bytes."""

    vectors: int | None = None
    bytes: int | None = None

    def fits(self, n: int, vector_bytes: int) -> bool:
        if self.vectors is None and self.bytes is None:
            raise ValueError("give the budget in vectors or in bytes")
        return (self.vectors is None or n <= self.vectors) and (self.bytes is None or n * vector_bytes <= self.bytes)


def plan_levels(n: int, share: float, budget: float, vector_bytes: float = 100.0) -> int:
    """Smallest number of levels, the root included, with n * share^(levels - 1) vectors inside the budget."""
    if not 0 < share < 1:
        raise ValueError("the density lies in (0, 1)")
    levels = 1
    while n * share ** (levels - 1) * vector_bytes > budget:
        levels += 1
    return levels


@dataclass
class LeveledIndex:
    """Member tables from the leaf (0) up, and the root set above them.

    `versions` are the folders that hold them, oldest first: changed partitions are written anew by
    later versions, and a reader takes each partition from the last version that touched it.
    """

    spark: SparkSession
    path: str
    counts: list[int]
    partitions: list[int]
    metric: str = "l2sq"
    graph_settings: dict = field(default_factory=dict)
    buckets: list[list[int]] = field(default_factory=list)
    width: str = "f8"
    versions: list[str] = field(default_factory=list)
    _graph: Graph | None = None

    def __post_init__(self) -> None:
        self.versions = self.versions or [self.path]

    @property
    def levels(self) -> int:
        return len(self.counts)

    def _latest(self, read, level: int) -> DataFrame:
        out, later = None, None
        for i in range(len(self.versions) - 1, -1, -1):
            rows = read(self.spark, self.versions[i], level, self.buckets[i][level])
            if later is not None:
                rows = rows.join(later, "pid", "left_anti")
            out = rows if out is None else out.unionByName(rows)
            if i:
                touched = store.read_touched(self.spark, self.versions[i], level)
                later = touched if later is None else later.union(touched)
        return out

    def members(self, level: int) -> DataFrame:
        """pid, vec_id, vec of a level below the root."""
        return self._latest(store.read_level, level)

    def packed(self, level: int) -> DataFrame:
        return self._latest(store.read_packed, level)

    def root(self) -> DataFrame:
        return store.read_root(self.spark, self.path)

    @property
    def graph(self) -> Graph:
        """The root's graph, built on first use and again after a loss: it depends on the stored root alone."""
        if self._graph is None:
            self._graph = build_graph(self.root(), metric=self.metric, **self.graph_settings)
        return self._graph

    def save_manifest(self) -> None:
        store.write_manifest(self.spark, self.path, {"counts": self.counts, "partitions": self.partitions, "metric": self.metric, "graph": self.graph_settings, "buckets": self.buckets, "width": self.width, "versions": self.versions})

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> "LeveledIndex":
        m = store.read_manifest(spark, path)
        return cls(spark, path, m["counts"], m["partitions"], m["metric"], m["graph"], m["buckets"], m["width"], m["versions"])

    def __repr__(self) -> str:
        return f"LeveledIndex({json.dumps({'counts': self.counts, 'partitions': self.partitions})})"


def build_index(vs: DataFrame, budget: RootBudget, density=0.1, metric: str = "l2sq", cells: int | None = None, max_copies: int = 1, eps: float = 0.1, algorithm: str = "lloyd", path: str | None = None, graph: dict | None = None, tolerance: float = 1.5, levels: int | None = None, width: str = "f8", centres=None) -> LeveledIndex:
    """`density` is one number, a list by level (the last one repeats), or 'auto' to profile each level on a sample.

    `levels` fixes the number of levels, the root included, in place of the budget; `width` is how
    components are stored ('u1', 'i1', 'f4', 'f8').  `centres` are the set's `coarse_centres`, if known.  The algorithm 'stride' takes keys as centroids.
    """
    if width not in store.WIDTHS:
        raise ValueError(f"the width is one of {sorted(store.WIDTHS)}")
    spark = vs.sparkSession
    path = path or scratch.path(spark, "index")
    current = vs.select("vec_id", "vec")
    counts, partitions, buckets, level, stride = [], [], [], 0, 1.0
    n = current.count()
    dim = current.select(F.size("vec").alias("d")).first()
    size = store.WIDTHS[width] * (dim["d"] if dim else 1) + 8
    while True:
        counts.append(n)
        if len(counts) >= levels if levels else budget.fits(n, size):
            store.write_root(current, path)
            break
        share = pick_density(current, density, level, metric, tolerance)
        stride /= share
        members = cluster.stride_members(current, round(stride)) if algorithm == "stride" else cluster.partition(current, share, cells if level == 0 else None, eps, max_copies, algorithm, centres=centres if level == 0 else None)
        buckets.append(store.buckets_for(spark, n))
        store.write_level(members, path, level, buckets[-1], width)
        stored = store.read_level(spark, path, level, buckets[-1])
        centres = stored.where("pid = vec_id").select("vec_id", "vec").dropDuplicates(["vec_id"])
        smaller = centres.count()
        if smaller >= n:
            raise ValueError(f"level {level} did not get smaller ({n} vectors, {smaller} partitions); choose a lower density")
        partitions.append(smaller)
        current, n, level = centres, smaller, level + 1
    index = LeveledIndex(spark, path, counts, partitions, metric, graph or {}, [buckets], width)
    index.save_manifest()
    return index


def shallower(index: LeveledIndex, levels: int) -> LeveledIndex:
    """The index that a build with fewer levels gives: the same lower levels, under a root of what the next level up holds."""
    if not 2 <= levels <= index.levels:
        raise ValueError("at least two levels and no more than there are")
    if levels == index.levels:
        return index
    path = scratch.path(index.spark, "index")
    store.write_root(index.members(levels - 1).select("vec_id", "vec"), path)
    out = LeveledIndex(index.spark, path, index.counts[:levels], index.partitions[: levels - 1], index.metric, index.graph_settings, [b[: levels - 1] for b in index.buckets], index.width, index.versions)
    out.save_manifest()
    return out


def verify_index(index: LeveledIndex) -> DataFrame:
    """Per level: members, partitions, partitions without their own centroid, and centroids that the level above misses; what recovery checks before it serves."""
    out = None
    for level in range(index.levels - 1):
        members = index.members(level)
        heads = members.where("pid = vec_id").select("pid").distinct()
        above = index.root().select(F.col("vec_id").alias("pid")) if level == index.levels - 2 else index.members(level + 1).select(F.col("vec_id").alias("pid")).distinct()
        lone = members.select("pid").distinct().join(heads, "pid", "left_anti").agg(F.count("*").alias("headless"))
        lost = heads.join(above, "pid", "left_anti").agg(F.count("*").alias("unlisted"))
        extra = above.join(heads, "pid", "left_anti").agg(F.count("*").alias("stale"))
        whole = members.agg(F.countDistinct("vec_id").alias("vectors"), F.countDistinct("pid").alias("partitions"))
        part = whole.join(lone).join(lost).join(extra).withColumn("level", F.lit(level))
        out = part if out is None else out.unionByName(part)
    return out


def pick_density(vs: DataFrame, density, level: int, metric: str, tolerance: float) -> float:
    if density == "auto":
        from levelindex.operators.granularity import determine_density

        return determine_density(vs, metric=metric, tolerance=tolerance).density
    if isinstance(density, (list, tuple)):
        return density[min(level, len(density) - 1)]
    return density


def footprint(index: LeveledIndex) -> DataFrame:
    """Vectors, partitions and stored bytes by level (packed partitions; the root as it is kept in memory: vectors, ids and links of its graph, which is measured here even where it is too large to be searched)."""
    rows = []
    dim = index.root().select(F.size("vec").alias("d")).first()["d"]
    links = links_held(index.root(), metric=index.metric, **index.graph_settings)
    for i, n in enumerate(index.counts):
        below = i < len(index.partitions)
        size = sum(store.stored_bytes(index.spark, f"{v}/packed/{i}") for v in index.versions) if below else n * dim * store.WIDTHS[index.width] + 8 * (n + links)
        rows.append((i, n, index.partitions[i] if below else 0, size))
    df = index.spark.createDataFrame(rows, "level int, vectors long, partitions long, bytes long")
    return df.withColumn("share", F.col("vectors") / index.counts[0])
