"""Closed-form cost of the leveled index at any scale, as expressions over a grid of settings.

Constants are assumptions, kept in `Hardware`; only shapes are claimed: reads bound the throughput,
nodes add it nearly in proportion, a level adds one round of latency, imbalance divides throughput.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Hardware:
    """Per node; assumed values of a storage server with local flash."""

    iops: int = 400_000
    disk_mb: int = 4_000
    net_mb: int = 1_500
    cores: int = 16
    distances_per_core_s: int = 20_000_000
    rtt_us: int = 150
    io_us: int = 120


def reply_bytes(n: int) -> int:
    """Eight bytes of id and four of distance for each result."""
    return 12 * n


def raw_bytes(m: int, share: float, dim: int, itemsize: int) -> float:
    """Whole partitions of one round."""
    return m / share * (dim * itemsize + 8)


def simulate(grid: DataFrame, hw: Hardware = Hardware(), dim: int = 128, itemsize: int = 1) -> DataFrame:
    """Grid columns: vectors, nodes, budget_bytes, per_hundred (density in percent), m, beta_tenths. Whole numbers throughout."""
    width = dim * itemsize + 8
    out = grid
    # levels: the smallest number whose root fits; the density is a percentage, so products stay exact
    level = F.lit(0)
    size = F.col("vectors").cast("double")
    for i in range(1, 9):
        fits = size * 100 <= F.col("budget_bytes")
        level = F.when((level == 0) & fits, F.lit(i)).otherwise(level)
        size = size * F.col("per_hundred") / 100
    out = out.withColumn("levels", level)
    below = F.col("levels") - 1
    out = out.withColumn("io", F.col("m") * below)
    out = out.withColumn("read_bytes", F.col("io") * (100 * width) / F.col("per_hundred"))
    out = out.withColumn("net_bytes", below * 12 * F.col("m") + below * width * 4)
    out = out.withColumn("evals", F.col("io") * 100 / F.col("per_hundred") + 2000)
    nodes, beta = F.col("nodes"), F.col("beta_tenths") / 10
    caps = {"iops": F.lit(hw.iops) * nodes / F.nullif("io", F.lit(0)), "disk": F.lit(hw.disk_mb * 1e6) * nodes / F.nullif("read_bytes", F.lit(0.0)), "net": F.lit(hw.net_mb * 1e6) * nodes / F.nullif("net_bytes", F.lit(0)), "cpu": F.lit(hw.cores * float(hw.distances_per_core_s)) * nodes / F.col("evals")}
    qps = F.least(*caps.values()) / beta
    out = out.withColumn("qps", F.round(qps, 3))
    name = F.lit(None).cast("string")
    for n, c in reversed(caps.items()):
        name = F.when(c == F.least(*caps.values()), F.lit(n)).otherwise(name)
    out = out.withColumn("bottleneck", name)
    out = out.withColumn("net_use", F.round(qps / caps["net"], 4)).withColumn("cpu_use", F.round(qps / caps["cpu"], 4))
    wait = F.ceil(F.col("m") / nodes) * hw.io_us * beta
    return out.withColumn("latency_us", F.round(hw.rtt_us + below * (hw.rtt_us + wait), 3))


def scale_grid(spark: SparkSession, start: int = 1_000_000_000) -> DataFrame:
    """Vectors from `start` to 1024 times as many with nodes in proportion (five at the start), two budgets (4 and 512 bytes a vector of the start), two imbalances."""
    size = spark.range(11).select((F.lit(start) * F.pow(F.lit(2), "id")).cast("long").alias("vectors"))
    more = spark.createDataFrame([(b * start, t) for b in (4, 512) for t in (10, 12)], "budget_bytes long, beta_tenths int")
    return size.crossJoin(F.broadcast(more)).withColumn("nodes", F.ceil(F.col("vectors") * 5 / start).cast("long")).withColumn("per_hundred", F.lit(10)).withColumn("m", F.lit(256))


def model_error(modelled: float, measured: float) -> float:
    return abs(modelled - measured) / measured
