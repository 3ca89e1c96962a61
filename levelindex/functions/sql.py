"""SQL names of the vector functions, an aggregate, and a table function over a saved index."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

FUNCTIONS = {
    "vec_ip": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_l2sq": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)",
    "vec_norm": "(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
    "vec_cosine": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1D - aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x) / sqrt(aggregate(a, 0D, (s, x) -> s + x * x) * aggregate(b, 0D, (s, x) -> s + x * x))",
}


def register(spark: SparkSession) -> list[str]:
    """Temporary SQL functions that Catalyst inlines."""
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    return list(FUNCTIONS)


@F.pandas_udf(ArrayType(DoubleType()))
def vec_mean(v: pd.Series) -> list:
    """Mean vector of a group whose size is bounded; for large groups use `mean_by`."""
    return np.mean(np.array(v.tolist(), float), axis=0).tolist()


def mean_by(df: DataFrame, *by: str) -> DataFrame:
    """Mean vectors with partial sums before the exchange."""
    parts = df.select(*by, F.posexplode("vec").alias("i", "x")).groupBy(*by, "i").agg(F.avg("x").alias("x"))
    return parts.groupBy(*by).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("vec"))


def ann_search(spark: SparkSession, path: str, queries: DataFrame, k: int = 10, m: int = 64) -> DataFrame:
    """Search a saved index by its path."""
    from levelindex.operators.build import LeveledIndex
    from levelindex.operators.search import search

    return search(LeveledIndex.load(spark, path), queries, k, m)


def register_ann_search(spark: SparkSession, path: str, name: str = "ann_search", m: int = 64) -> None:
    """SELECT * FROM name(TABLE(queries), k): a table function that takes each query down the whole index, reading
    the partitions it probes through Arrow. For batches `ann_search` is the faster way. One version only."""
    from levelindex.operators.build import LeveledIndex

    index = LeveledIndex.load(spark, path)
    if len(index.versions) > 1:
        raise ValueError("compact the index first")
    graph, below, width, metric = index.graph, index.levels - 1, index.width, index.metric

    class IndexSearch:
        def eval(self, row, k: int):
            import pyarrow.dataset as ds

            from levelindex.functions import distance
            from levelindex.sources.partition_source import file_system
            from levelindex.sources.store import unpack

            q = np.array(row["qvec"], float)
            rows, d, _, _ = graph.search(q, max(k, m))
            ids = graph.ids[rows]
            for level in range(below - 1, -1, -1):
                files, where = file_system(f"{path}/packed/{level}")
                level_rows = ds.dataset(where, format="parquet", filesystem=files, exclude_invalid_files=True)
                found = level_rows.to_table(filter=ds.field("pid").isin(ids[:m].tolist())).to_pylist()
                parts = [unpack(r["n"], r["ids"], r["block"], width) for r in found]
                ids = np.concatenate([p[0] for p in parts]) if parts else ids[:0]
                d = distance.block(metric, q[None], np.concatenate([p[1] for p in parts]))[0] if parts else d[:0]
                order = np.lexsort((ids, d))
                ids, d = ids[order], d[order]
            for i, (v, x) in enumerate(zip(ids[:k].tolist(), d[:k].tolist())):
                yield int(row["qid"]), i + 1, v, x

    spark.udtf.register(name, F.udtf(IndexSearch, returnType="qid long, rank int, vec_id long, dist double"))
