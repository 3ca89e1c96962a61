"""Stored levels: member rows for SQL, packed partition objects for search, the root, the manifest.

Both forms are dealt into buckets by pid, sorted inside files, and carry a bloom filter on pid, so that
a few pids read a few row groups.  Reading declares the buckets again (a catalog entry over the
path), so joins on pid need no exchange of the level.
"""

from __future__ import annotations

import hashlib
import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

MEMBERS = "pid long, vec_id long, vec array<double>"
PACKED = "pid long, n int, ids binary, block binary"
#: Widths in which components are stored; values must be exact in them.
WIDTHS = {"u1": 1, "i1": 1, "f4": 4, "f8": 8}
LEAST_BUCKET, MOST_BUCKET = 5_000, 1_000_000


def buckets_for(spark: SparkSession, rows: int) -> int:
    """Enough buckets for all cores unless they get tiny, and more where they would get large.

    Never one: Spark 4.1 takes a union of tables with a single bucket each for a single partition, and
    then aggregates its parts apart.
    """
    cores = spark.sparkContext.defaultParallelism
    return max(2, min(cores, -(-rows // LEAST_BUCKET)), min(100_000, -(-rows // MOST_BUCKET)))


def table_name(where: str) -> str:
    return "level_" + hashlib.md5(where.encode()).hexdigest()


def write_bucketed(df: DataFrame, where: str, buckets: int) -> None:
    """One file a bucket, sorted by pid, with bloom filters on pid."""
    dealt = df.repartition(buckets, "pid")
    writer = dealt.write.mode("overwrite").format("parquet").option("parquet.bloom.filter.enabled#pid", "true").option("path", where)
    writer.bucketBy(buckets, "pid").sortBy("pid").saveAsTable(table_name(where))


def read_bucketed(spark: SparkSession, where: str, schema: str, buckets: int) -> DataFrame:
    """The rows with their buckets; another session declares the table over the same files."""
    name = table_name(where)
    if not spark.catalog.tableExists(name):
        columns = ", ".join(f"{c.split()[0]} {c.split()[1]}" for c in schema.split(", "))
        spark.sql(f"CREATE TABLE IF NOT EXISTS {name} ({columns}) USING parquet CLUSTERED BY (pid) SORTED BY (pid) INTO {buckets} BUCKETS LOCATION '{where}'")
    return spark.table(name)


def drop_entries(spark: SparkSession, path: str, levels: int) -> None:
    """Remove the catalog entries of a stored index; its files stay."""
    for kind in ("members", "packed"):
        for level in range(levels):
            spark.sql(f"DROP TABLE IF EXISTS {table_name(f'{path}/{kind}/{level}')}")


def write_level(members: DataFrame, path: str, level: int, buckets: int, width: str = "f8") -> None:
    """Dealt by pid once; the packed objects come from the stored buckets without another exchange."""
    write_bucketed(members.select("pid", "vec_id", "vec"), f"{path}/members/{level}", buckets)
    stored = read_level(members.sparkSession, path, level, buckets)
    write_bucketed(pack(stored, width), f"{path}/packed/{level}", buckets)


def flat_lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All numbers of a list column and the offsets of its rows."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    offsets = column.offsets.to_numpy()
    return column.values.to_numpy(zero_copy_only=False), offsets


def pack(members: DataFrame, width: str = "f8") -> DataFrame:
    """One row for each partition: ids and vectors as blocks of little-endian numbers.

    Rows come sorted by pid inside a task, so partitions pass by one after another; only those that end in a batch are held.
    """
    kind = "<" + width

    def row(pid, ids, vecs):
        return pid, sum(map(len, ids)), b"".join(x.astype("<i8").tobytes() for x in ids), b"".join(x.astype(kind).tobytes() for x in vecs)

    def batch_of(rows):
        pids, n, ids, blocks = zip(*rows)
        return pa.RecordBatch.from_arrays([pa.array(pids, pa.int64()), pa.array(n, pa.int32()), pa.array(ids, pa.binary()), pa.array(blocks, pa.binary())], ["pid", "n", "ids", "block"])

    def run(batches):
        last, ids, vecs = None, [], []
        for batch in batches:
            if not batch.num_rows:
                continue
            pid, vec_id = batch.column("pid").to_numpy(), batch.column("vec_id").to_numpy()
            values, at = flat_lists(batch.column("vec"))
            edges = [0, *(np.flatnonzero(pid[1:] != pid[:-1]) + 1).tolist(), len(pid)]
            done = []
            for a, b in zip(edges, edges[1:]):
                if pid[a] != last:
                    if ids:
                        done.append(row(last, ids, vecs))
                    last, ids, vecs = pid[a], [], []
                ids.append(vec_id[a:b])
                vecs.append(values[at[a] : at[b]])
            if done:
                yield batch_of(done)
        if ids:
            yield batch_of([row(last, ids, vecs)])

    return members.sortWithinPartitions("pid", "vec_id").mapInArrow(run, PACKED)


def unpack(n: int, ids: bytes, block: bytes, width: str = "f8") -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(ids, "<i8"), np.frombuffer(block, "<" + width).reshape(n, -1).astype(float, copy=False)


def read_level(spark: SparkSession, path: str, level: int, buckets: int) -> DataFrame:
    return read_bucketed(spark, f"{path}/members/{level}", MEMBERS, buckets)


def read_packed(spark: SparkSession, path: str, level: int, buckets: int) -> DataFrame:
    return read_bucketed(spark, f"{path}/packed/{level}", PACKED, buckets)


def read_partitions(spark: SparkSession, path: str, level: int, buckets: int, pids: list[int]) -> DataFrame:
    """Members of a few partitions: the literal list reaches the scan, which reads their buckets only; bloom filters skip row groups."""
    return read_level(spark, path, level, buckets).where(F.col("pid").isin([int(p) for p in pids]))


def write_touched(pids: DataFrame, path: str, level: int) -> None:
    pids.select("pid").write.mode("overwrite").parquet(f"{path}/touched/{level}")


def read_touched(spark: SparkSession, path: str, level: int) -> DataFrame:
    return spark.read.schema("pid long").parquet(f"{path}/touched/{level}")


def stored_bytes(spark: SparkSession, where: str) -> int:
    """Bytes of the files below a path, by the file system that holds it."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(where)
    return int(p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength())


def write_root(root: DataFrame, path: str) -> None:
    root.select("vec_id", "vec").write.mode("overwrite").parquet(f"{path}/root")


def read_root(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("vec_id long, vec array<double>").parquet(f"{path}/root")


def write_manifest(spark: SparkSession, path: str, content: dict) -> None:
    spark.createDataFrame([(json.dumps(content),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def read_manifest(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.text(f"{path}/manifest").first()["value"])
