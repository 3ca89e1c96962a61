"""What the text operators share: columns, Arrow batches, blocks of bounded size.

Rules that hold for every operator here: a null text counts as an empty one, only the named columns
are read (others may have any name), repeated rows are separate rows, and empty tables give empty
results with the same columns.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, MapType, StructField, StructType

UPPER = bytes(range(65, 91))
LOWER_TABLE = bytes.maketrans(UPPER, UPPER.lower())


def table(spark, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_and_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Just the key as a long and the text, null texts as empty ones."""
    return docs.select(
        docs[id_col].cast("long").alias("doc_id"),
        F.coalesce(docs[text_col].cast("string"), F.lit("")).alias("text"),
    )


def free_name(columns: Iterable[str], name: str) -> str:
    """The name, or one made from it, that no column has (letter case aside)."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def column(name: str) -> Column:
    """A column by its exact name, dots and signs included."""
    return F.col("`" + name.replace("`", "``") + "`")


def map_rows(df: DataFrame, run, schema: StructType) -> DataFrame:
    """`mapInArrow` for frames whose column names may have dots, which it can't resolve itself."""
    names, safe = [*df.columns, *schema.names], {}
    for c in names:
        if "." in c or "`" in c:
            safe[c] = free_name([*names, *safe.values()], c.replace(".", "_").replace("`", "_"))
    if not safe:
        return df.mapInArrow(run, schema)
    inner = StructType([StructField(safe.get(f.name, f.name), f.dataType, f.nullable) for f in schema])
    return df.toDF(*[safe.get(c, c) for c in df.columns]).mapInArrow(run, inner).toDF(*schema.names)


def row_hash(df: DataFrame, leave: Iterable[str] = ()) -> Column:
    """A hash over the columns; those whose type has no hash (maps) count by their JSON form."""
    plain = lambda t: not isinstance(t, MapType) and not (isinstance(t, ArrayType) and not plain(t.elementType)) and not (isinstance(t, StructType) and not all(plain(f.dataType) for f in t)) and t.typeName() != "variant"
    return F.xxhash64(*[column(f.name) if plain(f.dataType) else F.to_json(F.struct(column(f.name))) for f in df.schema if f.name not in set(leave)])


def fold(doc_id: Column, n: int) -> Column:
    """The remainder of crc32 of the key as text; null for a null key."""
    return F.crc32(doc_id.cast("string")) % n


def raw_texts(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of an Arrow string column, nulls as empty."""
    return [x or b"" for x in pc.cast(column, pa.binary()).to_pylist()]


def small_batches(batches: Iterable[pa.RecordBatch], column: str, limit: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """Cut batches so that each holds about `limit` bytes of `column`; one row may be longer."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        if sizes.sum() <= limit:
            yield batch
            continue
        begin, held = 0, 0
        for i, n in enumerate(sizes):
            if held and held + n > limit:
                yield batch.slice(begin, i - begin)
                begin, held = i, 0
            held += int(n)
        yield batch.slice(begin)


def tidy() -> None:
    """Give freed memory back to the system: workers are used again by later tasks."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def by_length(lengths: np.ndarray) -> np.ndarray:
    """Order of rows from the longest to the shortest, for loops over positions."""
    return np.argsort(-lengths, kind="stable")


def binary_rows(schema: pa.Schema, columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema)], schema=schema)
