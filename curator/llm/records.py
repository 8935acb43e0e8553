"""Length-delimited binary token records with an offset index (operator 3).

File format, all integers little-endian.  A record is

    length   unsigned 64-bit   bytes of the payload
    check    unsigned 32-bit   masked CRC-32 of the eight length bytes
    payload  token ids, unsigned 16-bit if the vocabulary fits, else unsigned 32-bit
    check    unsigned 32-bit   masked CRC-32 of the payload

A masked checksum is the CRC rotated right by 15 bits plus 0xA282EAD8, modulo 2^32, so that checksums of data that hold
checksums stay sound.  Shards hold consecutive documents in id order.  The index is a Parquet table, one row a record,
written through Spark's commit protocol after the shards: it names only files of tasks that succeeded, so a
task that ran twice leaves an unnamed file and no wrong row.  A reader may shuffle index rows and fetch records by offset.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .pretokens import bytes_memo, strides, tokenizer
from .scratch import fresh_path

#: Fixed values of the format.
HEAD, TAIL, MASK_DELTA = struct.Struct("<QI"), struct.Struct("<I"), 0xA282EAD8

_INDEX = "id long, shard int, file string, offset long, n_bytes long, n_tokens long, before long"


def masked_crc(data: bytes) -> int:
    crc = zlib.crc32(data)
    return (((crc >> 15) | (crc << 17)) + MASK_DELTA) & 0xFFFFFFFF


def frame(payload: bytes) -> bytes:
    size = len(payload).to_bytes(8, "little")
    return size + TAIL.pack(masked_crc(size)) + payload + TAIL.pack(masked_crc(payload))


def unframe(data: bytes) -> bytes:
    """Payload of one framed record; raises ValueError if it is damaged."""
    if len(data) < HEAD.size + TAIL.size:
        raise ValueError("record is cut short")
    size, check = HEAD.unpack_from(data)
    if check != masked_crc(data[:8]) or len(data) != HEAD.size + size + TAIL.size:
        raise ValueError("record length is damaged")
    payload = data[HEAD.size : HEAD.size + size]
    if TAIL.unpack_from(data, HEAD.size + size)[0] != masked_crc(payload):
        raise ValueError("record payload is damaged")
    return payload


def _filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def id_type(model_path: str) -> str:
    return "<u2" if tokenizer(model_path).get_vocab_size(with_added_tokens=True) <= 1 << 16 else "<u4"


def write_records(docs: DataFrame, path: str, model_path: str, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode, frame and write ``docs`` below ``path``; returns the index, read back from ``path/index``.

    Index: ``id, shard, file, offset, n_bytes`` (of the framed record), ``n_tokens`` and ``before`` (tokens before it in its shard).  Ids
    ascend over shards and within them, null first; equal ids are ordered by a hash of the text.  Null text is empty and, like it, holds
    the end id alone.  Other columns are ignored; an empty table writes an empty index.
    """
    kind = id_type(model_path)
    body = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("body")).withColumn("tie", F.xxhash64("body"))
    ordered = body.repartitionByRange("id", "tie").sortWithinPartitions("id", "tie")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shard = TaskContext.get().partitionId()
        memo = bytes_memo(model_path, kind)
        end, width = np.array([end_id], kind).tobytes(), np.dtype(kind).itemsize
        store, root = _filesystem(path)
        store.create_dir(f"{root}/shards", recursive=True)
        name = f"shards/{shard:06d}-{uuid.uuid4().hex}.rec"
        sink, offset, before = None, 0, 0
        try:
            for batch in batches:
                rows = []
                encoded = chain.from_iterable(memo.values_of(g) for g in strides(t.as_py() for t in batch.column(1)))
                for doc, made in zip(batch.column(0).to_pylist(), encoded, strict=True):
                    payload = b"".join([*made, end])
                    record = frame(payload)
                    sink = sink or store.open_output_stream(f"{root}/{name}")
                    sink.write(record)
                    rows.append((doc, shard, name, offset, len(record), len(payload) // width, before))
                    offset, before = offset + len(record), before + len(payload) // width
                columns = list(zip(*rows, strict=True)) or [()] * 7
                kinds = (pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["id", "shard", "file", "offset", "n_bytes", "n_tokens", "before"])
        finally:
            if sink:
                sink.close()

    ordered.select("id", "body").mapInArrow(run, _INDEX).write.parquet(f"{path}/index")
    return read_index(docs.sparkSession, path)


def read_index(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(_INDEX).parquet(f"{path}/index")


def with_start(index: DataFrame) -> DataFrame:
    """``index`` plus ``start``: tokens of all records before it, from one prefix sum over shard totals (a row per shard)."""
    totals = index.groupBy("shard").agg(F.sum("n_tokens").alias("n"))
    behind = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    base = totals.select("shard", F.coalesce(F.sum("n").over(behind), F.lit(0)).alias("base"))
    return index.join(base, "shard").withColumn("start", F.col("base") + F.col("before")).drop("base")


def read_records(index: DataFrame, path: str, kind: str = "<u2") -> DataFrame:
    """Rows of ``index`` plus ``ids_crc32`` and ``tokens`` (binary, unsigned 32-bit ids), fetched by offset and verified.

    Rows are gathered by file and read in offset order; any subset or order of index rows may be given.
    """
    names = ["id", "shard", "file", "offset", "n_bytes", "n_tokens", "before"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = _filesystem(path)
        name, source = None, None
        for batch in batches:
            sums, tokens = [], []
            for file, offset, size in zip(*(batch.column(i).to_pylist() for i in (2, 3, 4)), strict=True):
                if file != name:
                    name, source = file, store.open_input_file(f"{root}/{file}")
                source.seek(offset)
                ids = np.frombuffer(unframe(source.read(size)), kind).astype("<u4").tobytes()
                sums.append(zlib.crc32(ids))
                tokens.append(ids)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(sums, pa.int64()), pa.array(tokens, pa.binary())], [*names, "ids_crc32", "tokens"])

    return index.select(*names).repartition("file").sortWithinPartitions("file", "offset").mapInArrow(run, f"{_INDEX}, ids_crc32 long, tokens binary")


def digest(docs: DataFrame, model_path: str, end_id: int = 1) -> DataFrame:
    """Write ``docs`` as records to shared scratch space and return what the files hold: ``doc_id, start, n_tokens, ids_crc32``."""
    path = fresh_path(docs.sparkSession, "records")
    index = write_records(docs, path, model_path, end_id)
    read = read_records(index, path, id_type(model_path)).withColumn("n_tokens", (F.octet_length("tokens") / 4).cast("long")).drop("tokens")
    return with_start(read).select(F.col("id").alias("doc_id"), "start", "n_tokens", "ids_crc32")
