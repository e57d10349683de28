"""Learning tables from the given ones: row_id, features (array of doubles), y, and a split."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lossygrad.functions.uniform import uniform
from lossygrad.session import map_arrow
from lossygrad.sources import table

# Class numbers.
LANGS = ("en", "de", "fr", "es")
PLANTED = (1.0, -2.0, 0.5, 3.0, -1.0)
#: Event types that a one-hot step may tell apart.
MAX_KINDS = 1024
#: Share of rows held out.
HELD_OUT = 0.25


#: ``features`` as whole counts: ``size`` bytes each; a row's pieces (``windows``) are of unit length once unpacked.
PACKED = "struct<windows: int, size: int, counts: binary>"


def _packed(counts: np.ndarray) -> tuple[int, bytes]:
    """Bytes a count, and the counts."""
    size = 1 if counts.max(initial=0) < 256 else 2 if counts.max() < 65536 else 4
    return size, counts.astype(f"<u{size}").tobytes()


def unpacked(column: pa.StructArray) -> np.ndarray:
    """Rows of unit pieces from packed counts, equal to those that ``trigrams`` writes unpacked."""
    windows, sizes, counts = (column.field(i).to_pylist() for i in range(3))
    if not counts:
        return np.zeros((0, 0))
    if len(set(sizes)) == 1:
        made = np.frombuffer(b"".join(counts), f"<u{sizes[0]}").reshape(len(counts), -1).astype(float)
    else:
        made = np.stack([np.frombuffer(c, f"<u{s}").astype(float) for s, c in zip(sizes, counts, strict=True)])
    return _units(made, windows[0])


def _units(counts: np.ndarray, windows: int) -> np.ndarray:
    """Pieces of unit length, in place; squares of whole counts add up exactly in any order."""
    c = counts.reshape(len(counts), windows, -1)
    c /= np.maximum(np.sqrt(np.einsum("rwk,rwk->rw", c, c)), 1e-12)[:, :, None]
    return counts


def trigrams(texts: DataFrame, dim: int = 1024, windows: int = 1, planted: Callable[[np.ndarray], np.ndarray] | None = None, packed: bool = False) -> DataFrame:
    """row_id, y, split and ``features``: hashed byte trigrams of the whole text, of unit length.

    With ``windows``, those of each of so many equal pieces of the text, side by side, ``dim`` in all.
    ``planted`` makes y from the features instead.  ``packed`` keeps them as counts of mostly a byte, an eighth of the size,
    which ``optim.sgd`` unpacks by slices.
    ``texts``: row_id, text, y.  Copies, whole or with an edit after their first dozen words, fall on the
    same side of the split.
    """
    opening = F.array_join(F.slice(F.split(F.trim(F.lower(F.coalesce("text", F.lit("")))), r"\s+"), 1, 12), " ")
    per = dim // windows
    rows = texts.select("row_id", "y", F.when(uniform(F.lit("split"), opening) < HELD_OUT, "test").otherwise("train").alias("split"), F.col("text").cast("binary").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                b = whole.slice(at, 1024)
                counts = np.zeros((b.num_rows, dim), np.int64)
                for i, t in enumerate(b.column("text").to_pylist()):
                    counts[i] = np.concatenate([np.bincount(_hashed(piece, per), minlength=per) for piece in _pieces(t or b"", windows)])
                x = _units(counts.astype(float), windows)
                y = b.column("y").cast(pa.float64()) if planted is None else pa.array(planted(x))
                if packed:
                    sizes, kept = zip(*map(_packed, counts), strict=True)
                    features = pa.StructArray.from_arrays([pa.array([windows] * b.num_rows, pa.int32()), pa.array(sizes, pa.int32()), pa.array(kept, pa.binary())], names=["windows", "size", "counts"])
                else:
                    features = pa.ListArray.from_arrays(pa.array(np.arange(0, b.num_rows * dim + 1, dim), pa.int32()), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([b.column("row_id"), y, b.column("split"), features], names=["row_id", "y", "split", "features"])

    return map_arrow(rows, run, f"row_id bigint, y double, split string, features {PACKED if packed else 'array<double>'}")


def _hashed(text: bytes, dim: int) -> np.ndarray:
    """Cells of the byte trigrams of a text."""
    raw = np.frombuffer(text.lower(), np.uint8).astype(np.int64)
    return ((raw[:-2] * 31 + raw[1:-1]) * 131 + raw[2:]) * 2654435761 % 4294967296 % dim if len(raw) > 2 else np.zeros(0, np.int64)


def _pieces(text: bytes, windows: int) -> list[bytes]:
    cuts = [len(text) * i // windows for i in range(windows + 1)]
    return [text[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


#: Sparse ``features`` as whole counts: places are of ``wide`` bytes, counts of ``size``.
PACKED_SPARSE = "struct<wide: int, size: int, at: binary, counts: binary>"


def unpacked_sparse(column: pa.StructArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bounds of rows, places, and values of rows of unit length."""
    rows = list(zip(*(column.field(i).to_pylist() for i in range(4)), strict=True))
    at = [np.frombuffer(a, f"<u{w}").astype(np.int64) for w, _, a, _ in rows]
    counts = [np.frombuffer(c, f"<u{s}").astype(float) for _, s, _, c in rows]
    values = [c / np.sqrt(c @ c) for c in counts if len(c)]
    return np.concatenate([[0], np.cumsum([len(x) for x in at])]).astype(np.int64), np.concatenate([np.zeros(0, np.int64), *at]), np.concatenate([np.zeros(0), *values])


def sparse_trigrams(texts: DataFrame, dim: int, packed: bool = False) -> DataFrame:
    """row_id, y and ``features``: places and values of hashed byte trigrams of the whole text, of unit length.

    ``packed`` keeps counts for values, and short places, a quarter of the size."""
    wide = 2 if dim <= 1 << 16 else 4

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                b = whole.slice(at, 1024)
                found = [np.unique(_hashed(t or b"", dim), return_counts=True) for t in b.column("text").to_pylist()]
                if packed:
                    sizes, counts = zip(*(_packed(c) for _, c in found), strict=True)
                    cells = [pa.array([wide] * b.num_rows, pa.int32()), pa.array(sizes, pa.int32()), pa.array([p.astype(f"<u{wide}").tobytes() for p, _ in found], pa.binary()), pa.array(counts, pa.binary())]
                    features = pa.StructArray.from_arrays(cells, names=["wide", "size", "at", "counts"])
                    yield pa.RecordBatch.from_arrays([b.column("row_id"), b.column("y").cast(pa.float64()), features], names=["row_id", "y", "features"])
                    continue
                bounds = pa.array(np.concatenate([[0], np.cumsum([len(p) for p, _ in found])]), pa.int32())
                places = np.concatenate([np.zeros(0, np.int64), *(p for p, _ in found)])
                values = np.concatenate([np.zeros(0), *(c / np.sqrt(c @ c) for _, c in found if len(c))])
                features = pa.StructArray.from_arrays([pa.ListArray.from_arrays(bounds, pa.array(places, pa.int32())), pa.ListArray.from_arrays(bounds, pa.array(values))], names=["at", "value"])
                yield pa.RecordBatch.from_arrays([b.column("row_id"), b.column("y").cast(pa.float64()), features], names=["row_id", "y", "features"])

    rows = texts.select("row_id", "y", F.col("text").cast("binary").alias("text"))
    return map_arrow(rows, run, f"row_id bigint, y double, features {PACKED_SPARSE if packed else 'struct<at: array<int>, value: array<double>>'}")


def planted_classes(dim: int, classes: int, seed: int = 7) -> Callable[[np.ndarray], np.ndarray]:
    """The class of a row is that of its largest random projection: learnable, with margins too thin to be easy."""
    w = np.random.default_rng(seed).choice([-1.0, 1.0], (dim, classes))
    return lambda x: ((x - 1 / np.sqrt(dim)) @ w).argmax(axis=1).astype(float)


def planted_line(dim: int, seed: int = 7, noise: float = 0.05) -> Callable[[np.ndarray], np.ndarray]:
    """A linear function of the row and a little noise drawn from the row itself."""
    r = np.random.default_rng(seed)
    w, v = r.normal(size=dim), r.normal(size=dim)
    return lambda x: x @ w + noise * np.sin(1e4 * (x @ v))


def language_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    lang = F.array_position(F.array(*[F.lit(x) for x in LANGS]), F.col("lang")) - 1
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_id"), "text", lang.cast("double").alias("y")).where("y >= 0")


def quality_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels").where("quality is not null").select("doc_id", "quality")
    return table(spark, sf_dir, "documents").join(labels, "doc_id").select(F.col("doc_id").alias("row_id"), "text", F.col("quality").cast("double").alias("y"))


def planted_features() -> list[Column]:
    """Five columns of about unit size over lineitem, orders and part."""
    return [F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, F.col("o_totalprice") / 500000, F.col("p_size") / 50]


def planted(spark: SparkSession, sf_dir: str, noise: float = 0.1) -> DataFrame:
    """Least squares with a known answer: every line with its order and part; y from ``PLANTED`` and hashed noise."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_discount", "l_tax")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice")
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_size")
    joined = lines.join(orders, "l_orderkey").join(parts, "l_partkey")
    x = planted_features()
    target = sum((F.lit(w) * c for w, c in zip(PLANTED, x, strict=True)), F.lit(0.0))
    drawn = uniform(F.lit("noise"), F.col("l_orderkey"), F.col("l_linenumber"), F.col("l_partkey"), F.col("l_suppkey")) - 0.5
    return joined.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.array(*x).alias("features"), (target + F.lit(noise) * drawn).alias("y"))


def planted_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``planted`` with row_id from the row's keys (not dense)."""
    return planted(spark, sf_dir).select(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("row_id"), "features", "y")


def vectors_with_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as rows: labels carry no signal, so only fit may be read from them."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("row_id"), F.col("embedding").cast("array<double>").alias("features"), F.col("label").cast("double").alias("y"))


def sequences(spark: SparkSession, sf_dir: str, steps: int = 6) -> DataFrame:
    """Windows of a user's events in time order: features are the steps' types (one-hot) and values, y the next type."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type", "value")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(MAX_KINDS + 1).collect()]
    if len(kinds) > MAX_KINDS:
        raise ValueError(f"more than {MAX_KINDS} event types: not a vocabulary for one-hot steps")
    number = F.array_position(F.array(*[F.lit(k) for k in kinds]), F.col("event_type")) - 1
    hot = F.array(*[F.when(number == i, 1.0).otherwise(0.0) for i in range(len(kinds))], F.tanh(F.coalesce("value", F.lit(0.0)) / 100))
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    past = order.rowsBetween(-steps, -1)
    marked = e.withColumn("kind", number.cast("double")).withColumn("hot", hot)
    return marked.select(F.col("event_id").alias("row_id"), "user_id", F.flatten(F.collect_list("hot").over(past)).alias("features"), F.col("kind").alias("y"), F.count("*").over(past).alias("n_")).where(F.col("n_") == steps).drop("n_")
