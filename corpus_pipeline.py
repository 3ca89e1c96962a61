"""The corpus pipeline over `documents`: five stages, each written as Parquet and read by the next.

Toxic documents go; of each group of near duplicates the smallest key stays; byte strings that a
document with a smaller key has too are cut out (whole characters only); documents that contain a
benchmark item go; the rest is interleaved by source.  All stages but the last return the columns
of documents, `n_chars` following the text.

Cases: a null text counts as an empty one and stays null; rows with a null key are never dropped for
the sake of others; of rows that share key and text one stays; an empty table passes through; further
columns of any name and type come along.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType

from levelindex import scratch
from levelindex.llm import crf_toxicity, decontaminate, jaccard_groups, pfair_mix, suffix_dedup
from levelindex.llm.common import column, fold, free_name, map_rows, raw_texts, row_hash, small_batches, table, tidy


def drop_toxic(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score stays below 0.7; the model learns from the labels outside its held-out fold."""
    import numpy as np
    import pyarrow as pa

    rows = docs.select(docs.doc_id.cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    sample = crf_toxicity.labelled_texts(rows, table(spark, sf_dir, "labels"), lambda c: fold(c, 3) != 1, crf_toxicity.CrfSettings())
    model = crf_toxicity.fit([t for t, _ in sample], [y for _, y in sample], crf_toxicity.CrfSettings())
    if model is None:
        return docs
    sent = spark.sparkContext.broadcast((model.weights, model.bias, model.move, model.start, model.scale))

    def run(batches):
        own = crf_toxicity.Chain(*sent.value)
        for batch in small_batches(batches, "text", 2 << 20):
            score = own.scores(own.evidence(raw_texts(batch.column("text")))[0])
            yield batch.filter(pa.array(np.asarray(score < 0.7)))
        del own
        tidy()

    return map_rows(docs, run, docs.schema)


def drop_near_duplicates(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by a five-word Jaccard of at least 0.8: the smallest key, and one row of it; rows without any key in their group all stay."""
    groups = scratch.save(jaccard_groups.near_duplicates(docs), "groups")
    key, row, n, at = (free_name(docs.columns, x) for x in ("key", "row", "n", "at"))
    first = groups.where(F.col("doc_id") == F.col("component_id")).groupBy("root", "component_id", "row").agg(F.count("*").alias("n")).groupBy("root", "component_id").agg(F.min(F.struct("row", "n")).alias("k"))
    keys = scratch.save(first.select(F.col("component_id").alias(key), F.col("k.row").alias(row), F.col("k.n").alias(n)), "kept")
    own = [column(c) for c in docs.columns]
    marked = docs.withColumn(at, F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))))
    kept = marked.join(keys, (F.col("doc_id") == F.col(key)) & (F.col(at) == F.col(row)))
    if not keys.where(F.col(n) > 1).isEmpty():  # one of the rows that share key and text
        several = kept.where(F.col(n) > 1).withColumn(at, row_hash(docs)).select(*own, key, row, at)
        turn = F.row_number().over(Window.partitionBy(key, row).orderBy(at))
        one = several.withColumn(at, turn).where(F.col(at) == 1)
        kept = kept.where(F.col(n) == 1).select(own).unionByName(one.select(own))
    kept = kept.select(own)
    if not groups.where(F.col("component_id").isNull()).isEmpty():
        alone = groups.where(F.col("component_id").isNull()).select(F.col("row").alias(row)).distinct()
        kept = kept.unionByName(marked.where(F.col("doc_id").isNull()).join(alone, F.col(at) == F.col(row), "left_semi").select(own))
    return kept


def cut_repeats(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without byte strings of 50 or more that a document with a smaller key has; no character is split."""
    import pyarrow as pa

    mark = row_hash(docs, ("doc_id", "n_chars"))
    key, row, own, begins, ends = (free_name(docs.columns, x) for x in ("key", "row", "own", "begins", "ends"))
    rows = docs.select(docs.doc_id.cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), mark.alias("row"))
    spans = suffix_dedup.cut_repeats(rows, least=50, with_kept=False).where("n_removed > 0").select("doc_id", "row", "begins", "ends").dropDuplicates(["doc_id", "row"])
    spans = scratch.save(spans.toDF(key, row, begins, ends), "spans")
    marked = docs.withColumn(own, mark)
    joined = marked.join(spans, (F.col("doc_id") == F.col(key)) & (F.col(own) == F.col(row)), "left").select(*[column(c) for c in docs.columns], begins, ends)
    schema = docs.schema
    at, count = docs.columns.index("text"), docs.columns.index("n_chars") if "n_chars" in docs.columns else None

    def run(batches):
        for batch in small_batches(batches, "text"):
            texts, sizes = [], []
            for raw, null, a, b in zip(raw_texts(batch.column("text")), batch.column("text").is_null().to_pylist(), batch.column(begins).to_pylist(), batch.column(ends).to_pylist()):
                text = None if null else whole_characters(raw, a or [], b or [])
                texts.append(text)
                sizes.append(None if null else len(text))
            columns = batch.columns[: len(schema)]
            columns[at] = pa.array(texts, pa.string())
            if count is not None:
                columns[count] = pa.array(sizes, pa.int64())
            yield pa.RecordBatch.from_arrays(columns, batch.schema.names[: len(schema)])

    return map_rows(joined, run, schema)


def whole_characters(raw: bytes, begins: list[int], ends: list[int]) -> str:
    """What stays; a cut that begins or ends inside a character leaves that character."""
    out, last = [], 0
    for a, b in zip(begins, ends):
        while a < b and raw[a] & 0xC0 == 0x80:
            a += 1
        while b < len(raw) and b > a and raw[b] & 0xC0 == 0x80:
            b -= 1
        out.append(raw[last:a])
        last = b
    return b"".join([*out, raw[last:]]).decode()


def drop_leaks(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that align with no benchmark item."""
    return decontaminate.without_leaks(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with their block, slot and place in the mixture."""
    placed = pfair_mix.schedule(docs)
    return placed.drop(free_name(docs.columns, "mix_source"))


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_duplicates),
    ("suffix_array_dedup", cut_repeats),
    ("benchmark_decontamination", drop_leaks),
    ("mix_sources", mix_sources),
]

#: SQL can't express the fitted tagger and the fingerprints; tests/llm hold the stages against plain versions.
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    fields = {f.name: f.dataType for f in docs.schema}
    if not isinstance(fields.get("text"), StringType) or not isinstance(fields.get("doc_id"), LongType):
        docs = docs.withColumn("text", docs.text.cast("string")).withColumn("doc_id", docs.doc_id.cast("long"))
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
