"""Intermediate tables in the folder that the cluster shares.

A plan that is read more than once, or that a lost executor must not force to be rebuilt from the
start, is written as Parquet below ``spark.checkpoint.dir`` and read again.  That folder is the one
the session names; only a local session that names none (tests) gets a temporary folder.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_made: list[tuple[SparkSession, str]] = []
_fallback: list[str] = []


def root(spark: SparkSession) -> str:
    """The shared folder of the session."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("name a folder that all executors share in spark.checkpoint.dir")
    if not _fallback:
        _fallback.append("file://" + tempfile.mkdtemp(prefix="levelindex-"))
    return _fallback[0]


def path(spark: SparkSession, name: str) -> str:
    """A new path for a table; it is removed when the interpreter ends or by `purge`."""
    made = f"{root(spark)}/levelindex/{name}-{uuid.uuid4().hex[:12]}"
    _made.append((spark, made))
    return made


def save(df: DataFrame, name: str) -> DataFrame:
    """Write a frame and give back the stored one, with a plan that starts at the files."""
    spark = df.sparkSession
    where = path(spark, name)
    df.write.parquet(where)
    return spark.read.schema(df.schema).parquet(where)


def remove(spark: SparkSession, where: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(where)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def purge(keep: DataFrame | None = None) -> None:
    """Remove the tables made so far, except those that `keep` reads."""
    used = "\n".join(keep.inputFiles()) if keep is not None else ""
    for item in list(_made):
        spark, where = item
        if where.rsplit("/", 1)[-1] in used:
            continue
        _made.remove(item)
        try:
            remove(spark, where)
        except Exception:  # the session may be gone; a file left behind is not an error
            pass


atexit.register(purge)
