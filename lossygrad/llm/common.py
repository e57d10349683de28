"""Pieces that the operators of this package share.

Words are the maximal runs of anything but the six ASCII white-space characters,
which is exactly what ``bytes.split()`` returns for UTF-8 text.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from lossygrad.session import map_arrow, ship_package  # noqa: F401

#: Java pattern of one word.
WORD = r"[^\x20\x09-\x0D]+"


def session_of(df: DataFrame) -> SparkSession:
    return df.sparkSession


def shared_folder(spark: SparkSession) -> str:
    """URI of the folder that driver and executors share (``spark.checkpoint.dir``).

    Where the session names none, one that was set as the checkpoint directory is taken,
    or, if driver and executors are one process, as in tests, a temporary folder, once.
    On a cluster there is no such folder to fall back to.
    """
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="lossygrad-shared-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def fresh_path(spark: SparkSession, stem: str) -> str:
    """A new path in this application's part of the shared folder."""
    return f"{shared_folder(spark)}/{spark.sparkContext.applicationId}/{stem}-{uuid.uuid4().hex}"


def clear(spark: SparkSession) -> None:
    """Deletes all that this application has put in the shared folder; for when its results have been stored elsewhere."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_folder(spark)}/{spark.sparkContext.applicationId}")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def cut_lineage(df: DataFrame, compression: str = "snappy") -> DataFrame:
    """A reliable copy of ``df`` in the shared folder, read back with its schema."""
    spark = session_of(df)
    path = fresh_path(spark, "stage")
    df.write.option("compression", compression).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def utf8_bytes(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """The texts of a column as UTF-8; null is empty."""
    return [b"" if x is None else x for x in batch.column(name).cast(pa.binary()).to_pylist()]


def arrow_words(texts: pa.Array | pa.ChunkedArray) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Distinct words of a string array, the number of each word in order, and each text's bounds (n + 1 places)."""
    if isinstance(texts, pa.ChunkedArray):
        texts = (texts.cast(pa.large_string()) if texts.nbytes > 1 << 30 else texts).combine_chunks()
    split = pc.ascii_split_whitespace(pc.fill_null(texts, ""))
    bounds = split.offsets.to_numpy().astype(np.int64) - split.offsets[0].as_py() if len(texts) else np.zeros(1, np.int64)
    words = split.flatten()
    filled = pc.greater(pc.binary_length(words), 0)
    if not pc.all(filled).as_py():
        kept = np.concatenate([[0], np.cumsum(filled.to_numpy(zero_copy_only=False))])
        words, bounds = words.filter(filled), kept[bounds]
    coded = words.dictionary_encode()
    return coded.dictionary, coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), bounds


def word_count(text: Column) -> Column:
    """Number of words, as a long; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def crc_bucket(doc_id: Column, parts: int) -> Column:
    """CRC-32 of the id written as text, modulo ``parts``; a null id falls in bucket 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % parts, F.lit(0)).cast("int")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind ``value`` once and use it many times in ``body``.

    The optimizer may otherwise copy an expensive expression into every place
    (and every lambda step) that mentions it.
    """
    return F.element_at(F.transform(F.array(value), body), 1)


def only(df: DataFrame, *columns: str) -> DataFrame:
    """The named columns; a missing one is null, so odd tables don't crash."""
    have = set(df.columns)
    return df.select(*[F.col(f"`{c}`") if c in have else F.lit(None).cast("string").alias(c) for c in columns])


def guarded(docs: DataFrame) -> DataFrame:
    """``docs`` with all columns that operators don't read renamed, so that none clashes with a computed one."""
    read = ("doc_id", "text", "source")
    return docs.select(*[F.col(f"`{c}`").alias(c if c in read else f"kept_{i}_") for i, c in enumerate(docs.columns)])


def restored(df: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of ``guarded(docs)`` in ``df`` under their own names."""
    return df.select(*[F.col(f"`{a}`").alias(b) for a, b in zip(guarded(docs).columns, docs.columns, strict=True)])
