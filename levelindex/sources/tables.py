"""Vector sets made from the given tables: vec_id long, vec array<double>."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def valid(vs: DataFrame, dim: int | None = None, metric: str = "l2sq") -> DataFrame:
    """Rows that can be indexed: right length, no null, NaN or infinite component; not zero under cosine."""
    v = F.col("vec")
    ok = F.col("vec_id").isNotNull() & v.isNotNull() & F.forall(v, lambda x: F.coalesce(F.abs(x) < F.lit(1e300), F.lit(False)))
    if dim is not None:
        ok = ok & (F.size(v) == dim)
    if metric == "cosine":
        ok = ok & F.exists(v, lambda x: x != 0)
    return vs.where(ok)


def quantised(v: Column, signed: bool = False) -> Column:
    """Components in [-1, 1] as whole numbers: 0..255, or -127..127."""
    return F.transform(v, (lambda x: F.round(x.cast("double") * 127)) if signed else (lambda x: F.floor((x.cast("double") + 1) * 127.5).cast("double")))


def embeddings(spark: SparkSession, sf_dir: str, form: str = "float") -> DataFrame:
    """The given embeddings as floats, as 0..255 ('uint8') or as -127..127 ('int8')."""
    e = table(spark, sf_dir, "embeddings")
    v = e.embedding.cast("array<double>") if form == "float" else quantised(e.embedding, form == "int8")
    return e.select("vec_id", v.alias("vec"), "label")


def line_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole-number features of lineitem; the four keys together are unique, a repeated key counts once (told apart before the array is made: plain columns are hashed, arrays would be sorted)."""
    li = table(spark, sf_dir, "lineitem")
    key = ((F.col("l_orderkey").cast("long") * 8 + F.col("l_linenumber")) * 1048576 + F.col("l_partkey")) * 16384 + F.col("l_suppkey")
    parts = [
        F.floor(F.col("l_quantity") * 4),
        F.floor(F.col("l_extendedprice") / 400),
        F.floor(F.col("l_discount") * 1000 + 0.5),
        F.floor(F.col("l_tax") * 1000 + 0.5),
        F.floor(F.datediff(F.col("l_shipdate"), F.lit("1992-01-01")) / 10),
        F.pmod(F.col("l_partkey"), F.lit(211)),
        F.pmod(F.col("l_suppkey"), F.lit(101)),
    ]
    names = [f"x{i}" for i in range(len(parts))]
    once = li.select(key.alias("vec_id"), *[p.cast("double").alias(n) for p, n in zip(parts, names)], "l_orderkey").dropDuplicates(["vec_id"])
    return once.select("vec_id", F.array(*names).alias("vec"), "l_orderkey")


def word_buckets(df: DataFrame, id_col: str, text_col: str, dims: int = 64) -> DataFrame:
    """Counts of words in hashed buckets: a sparse aggregate turned into dense arrays."""
    words = df.select(F.col(id_col).alias("vec_id"), F.explode(F.split(F.lower(F.coalesce(text_col, F.lit(""))), r"[ \t\n\x0b\f\r]+")).alias("word")).where("word != ''")
    bucket = F.conv(F.substring(F.md5("word"), 1, 8), 16, 10).cast("long") % dims
    counts = words.groupBy("vec_id", bucket.cast("int").alias("bucket")).agg(F.count("*").cast("double").alias("n"))
    dense = counts.groupBy("vec_id").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "n"))).alias("m"))
    at = F.sequence(F.lit(0), F.lit(dims - 1))
    return dense.select("vec_id", F.transform(at, lambda i: F.coalesce(F.element_at("m", i), F.lit(0.0))).alias("vec"))


def normalised(vs: DataFrame) -> DataFrame:
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x * x))
    return vs.where(norm > 0).withColumn("vec", F.transform("vec", lambda x: x / norm))


def document_vectors(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    return word_buckets(table(spark, sf_dir, "documents"), "doc_id", "text", dims)


def page_vectors(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    plain = table(spark, sf_dir, "pages").select("page_id", F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
    return word_buckets(plain, "page_id", "text", dims)


def turn_vectors(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    c = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("vec_id"), "text")
    return word_buckets(c, "vec_id", "text", dims)


def event_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Value, hour on the circle, type and the number in props, with the event's time and user."""
    e = table(spark, sf_dir, "events")
    hour = F.hour("ts") * (3.141592653589793 / 12)
    kinds = [F.when(F.pmod(F.conv(F.substring(F.md5("event_type"), 1, 4), 16, 10).cast("int"), F.lit(5)) == i, 1.0).otherwise(0.0) for i in range(5)]
    k = F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0)) / 100
    return e.select(F.col("event_id").alias("vec_id"), F.array(F.col("value") / 100, F.sin(hour), F.cos(hour), *kinds, k).alias("vec"), F.col("ts").cast("timestamp").alias("ts"), "user_id")


def split_queries(vs: DataFrame, modulus: int = 50, held: int = 7) -> tuple[DataFrame, DataFrame]:
    """Base and queries: rows whose key has the remainder `held` ask."""
    asks = F.pmod(F.col("vec_id"), F.lit(modulus)) == held
    return vs.where(~asks), vs.where(asks).select(F.col("vec_id").alias("qid"), F.col("vec").alias("qvec"))
