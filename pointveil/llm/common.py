"""Shared pieces of the corpus operators: folds, staging, bounded samples, Arrow batching."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one numpy pass handles; bounds a Python worker's memory.
CHUNK_BYTES = 4 << 20


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The documents table of a data folder."""
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The labels table of a data folder."""
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def fold(doc_id: Column, folds: int) -> Column:
    """crc32 of the id as text, modulo ``folds``; a null id is fold 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % folds, F.lit(0))


def free_name(df: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of ``df`` has it (column names are compared without case)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def row_key(doc_id: Column, sha_hex: Column) -> Column:
    """The identity of a row by its id (which may be null) and its text's SHA-256."""
    return F.concat_ws("|", F.coalesce(doc_id.cast("string"), F.lit("-")), sha_hex)


def shared_dir(spark: SparkSession) -> str:
    """A fresh folder below spark.checkpoint.dir; the local temp folder where that is unset (tests)."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = tempfile.gettempdir() + "/pointveil-stage"
    return f"{root.rstrip('/')}/{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"


def staged(df: DataFrame) -> DataFrame:
    """Cut lineage: write ``df`` as Parquet in the shared folder and read it back."""
    spark = df.sparkSession
    path = shared_dir(spark)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def labelled_sample(docs: DataFrame, marks: DataFrame, label: str, held_fold: int, folds: int, bound: int) -> list:
    """At most ``bound`` rows (doc_id, text, label) whose fold is not ``held_fold``, by smallest id hash.

    The sample is chosen on the narrow labels table (top-k), so the semi-join side is bounded by ``bound``.
    Rows with a null id or label are not used.
    """
    rank = F.xxhash64(F.col("doc_id"), F.lit(17))
    keep = (
        marks.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & (fold(F.col("doc_id"), folds) != held_fold))
        .select("doc_id", F.col(label).cast("int").alias("label"))
        .dropDuplicates(["doc_id"])
        .orderBy(rank, "doc_id")
        .limit(bound)
    )
    rows = docs.select("doc_id", "text").join(F.broadcast(keep), "doc_id").collect()
    return sorted(((r.doc_id, r.text or "", r.label) for r in rows), key=lambda r: (r[0], r[1]))


def byte_chunks(batch: pa.RecordBatch, column: str = "text", limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of rows of about ``limit`` bytes of text; a longer text stands alone."""
    import pyarrow.compute as pc

    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    start, total = 0, 0
    for i, n in enumerate(sizes):
        if total and total + n > limit:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += int(n)
    if start < batch.num_rows:
        yield batch.slice(start)


def texts_of(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    """The texts as UTF-8 bytes; null counts as empty."""
    return [x or b"" for x in batch.column(column).cast(pa.binary()).to_pylist()]
