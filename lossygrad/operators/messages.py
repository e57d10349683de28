"""Messages: one row a worker and bucket, with the payload in bytes; encoded before a shuffle, decoded after."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lossygrad.session import map_arrow
from lossygrad.operators import kernels
from lossygrad.sources import MESSAGES

_KINDS = [pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.float32(), pa.int32(), pa.int32(), pa.int64(), pa.binary()]
_NAMES = [x.split()[0] for x in MESSAGES.split(", ")]


def batch_of(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [[] for _ in _KINDS]
    return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, _KINDS, strict=True)], names=_NAMES)


def encode(quantized: DataFrame, codec: str = "gap", bits: int = 4, round_: int = 0) -> DataFrame:
    """Messages of a quantized DataFrame (``shard`` or vec_id is the sender, bucket_id or 0 the bucket)."""
    if codec not in kernels.CODECS or codec == "float32":
        raise ValueError(f"unknown codec {codec}")
    shard = F.col("shard") if "shard" in quantized.columns else F.col("vec_id")
    bucket = F.col("bucket_id") if "bucket_id" in quantized.columns else F.lit(0)
    rows = quantized.select(shard.cast("int").alias("shard"), bucket.cast("bigint").alias("bucket_id"), "scale", "sign", "level")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for shard, bucket, scale, sign, level in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                sg, lv = np.array(sign, np.int8), np.array(level, np.int32)
                name, n_bits, payload = kernels.encode(codec, scale, sg, lv, bits)
                out.append((round_, shard, bucket, name, scale, len(lv), int((lv > 0).sum()), n_bits, payload))
            yield batch_of(out)

    return map_arrow(rows, run, MESSAGES)


def decode(messages: DataFrame, bits: int = 4, header: int = 0) -> DataFrame:
    """round, shard, bucket_id, scale, sign, level."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            signs, levels, scales = [], [], []
            for codec, n, n_bits, payload in zip(*(b.column(c).to_pylist() for c in ("codec", "n", "n_bits", "payload")), strict=True):
                scale, sign, level = kernels.decode(codec, payload, n, n_bits - header, bits)
                scales.append(float(scale))
                signs.append(sign.tolist())
                levels.append(level.tolist())
            yield pa.RecordBatch.from_arrays(
                [b.column("round"), b.column("shard"), b.column("bucket_id"), pa.array(scales, pa.float32()), pa.array(signs, pa.list_(pa.int8())), pa.array(levels, pa.list_(pa.int32()))],
                names=["round", "shard", "bucket_id", "scale", "sign", "level"],
            )

    return map_arrow(messages, run, "round int, shard int, bucket_id bigint, scale float, sign array<tinyint>, level array<int>")


def by_bucket(messages: DataFrame, partitions: int | None = None) -> DataFrame:
    """The one large exchange: encoded payloads to the task that owns their bucket."""
    return messages.repartition(partitions, "bucket_id") if partitions else messages.repartition("bucket_id")
