"""Operator 3: token ids as length-delimited binary records with masked checksums and an offset index.

A shard is a run of records in ascending doc_id order. A record frames one document's ids:

    8 bytes   length of the payload, little-endian
    4 bytes   masked CRC-32C of those 8 bytes
    n bytes   payload: the ids, little-endian, 2 bytes each where every id fits, otherwise 4
    4 bytes   masked CRC-32C of the payload

The index is a Parquet table beside the shards (shard, row, doc_id, offset, length, n_tokens) for shuffled reads.
Shards are written under a name of the task's attempt and then renamed: an attempt that breaks off leaves no shard.
Readers open the shards that the index names, and the index holds those of committed tasks alone; the shard of an
attempt that ended but wasn't committed may stay in the folder, unread.
"""

from __future__ import annotations

import functools
import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import release_memory, scratch, small_batches
from .tokenization import encoder, row_slices

#: Reversed CRC-32C polynomial and the mask's constant (fixed values of the public record format).
POLYNOMIAL = 0x82F63B78
MASK_DELTA = 0xA282EAD8
_BLOCK = 256


@functools.cache
def _byte_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint32)
    for _ in range(8):
        t = np.where(t & 1, (t >> 1) ^ np.uint32(POLYNOMIAL), t >> 1)
    return t


@functools.cache
def _shift(n: int) -> np.ndarray:
    """Tables (4, 256) that give a checksum state followed by n zero bytes; n is a power of two."""
    t = _byte_table()
    if n == 1:
        states = np.arange(256, dtype=np.uint32)[None, :] << (np.arange(4, dtype=np.uint32) * 8)[:, None]
        return t[states & 255] ^ (states >> 8)
    half = _shift(n // 2)
    return _apply(half, half)


def _apply(tables: np.ndarray, x: np.ndarray) -> np.ndarray:
    return tables[0][x & 255] ^ tables[1][(x >> 8) & 255] ^ tables[2][(x >> 16) & 255] ^ tables[3][x >> 24]


@functools.cache
def _word_tables() -> tuple[np.ndarray, np.ndarray]:
    """_shift(4) for the low and the high half of a state."""
    x, t = np.arange(1 << 16), _shift(4)
    return t[0][x & 255] ^ t[1][x >> 8], t[2][x & 255] ^ t[3][x >> 8]


def crc32c(payloads: list[bytes]) -> np.ndarray:
    """CRC-32C of many byte strings at once: all blocks word by word, then each string's blocks in order."""
    sizes = np.array([len(p) for p in payloads], np.int64)
    width = min(_BLOCK, max(4, 1 << int(sizes.max(initial=0) - 1).bit_length()))
    blocks = np.maximum(1, -(-sizes // width))
    ends = np.cumsum(blocks)
    buf = np.zeros(int(ends[-1]) * width if len(ends) else 0, np.uint8)
    for p, n, stop in zip(payloads, sizes.tolist(), (ends * width).tolist()):  # right-aligned: leading zeros leave an empty state as it is
        raw = np.frombuffer(p, np.uint8)
        buf[stop - n : stop] = raw
        head = min(4, n)
        buf[stop - n : stop - n + head] ^= 255
    low, high = _word_tables()
    state = np.zeros(len(buf) // width, np.uint32)
    for word in np.ascontiguousarray(buf.view("<u4").reshape(-1, width // 4).T):
        halves = (state ^ word).view("<u2")
        state = low.take(halves[::2]) ^ high.take(halves[1::2])
    out = np.zeros(len(payloads), np.uint32)
    starts = ends - blocks
    for step in range(int(blocks.max()) if len(blocks) else 0):
        live = np.nonzero(blocks > step)[0]
        out[live] = _apply(_shift(width), out[live]) ^ state[starts[live] + step]
    for i in np.nonzero(sizes < 4)[0]:  # the initial state reaches past the end of very short strings
        crc = 0xFFFFFFFF
        for b in payloads[i]:
            crc = int(_byte_table()[(crc ^ b) & 255]) ^ (crc >> 8)
        out[i] = crc
    return out ^ np.uint32(0xFFFFFFFF)


def masked(crc: np.ndarray) -> np.ndarray:
    return ((crc >> 15) | (crc << 17)) + np.uint32(MASK_DELTA)


def frame(payloads: list[bytes]) -> list[bytes]:
    heads = [struct.pack("<Q", len(p)) for p in payloads]
    a, b = masked(crc32c(heads)), masked(crc32c(payloads))
    return [h + struct.pack("<I", x) + p + struct.pack("<I", y) for h, x, p, y in zip(heads, a.tolist(), payloads, b.tolist())]


def unframe(data: bytes, offset: int = 0) -> bytes:
    """The payload of the record at offset; raises ValueError when a length or checksum is wrong."""
    head = data[offset : offset + 8]
    (n,), (a,) = struct.unpack("<Q", head), struct.unpack("<I", data[offset + 8 : offset + 12])
    payload = data[offset + 12 : offset + 12 + n]
    (b,) = struct.unpack("<I", data[offset + 12 + n : offset + 16 + n])
    want = masked(crc32c([head, payload]))
    if (a, b) != (int(want[0]), int(want[1])) or len(payload) != n:
        raise ValueError(f"bad record at {offset}")
    return payload


def _fs(uri: str):
    return pafs.FileSystem.from_uri(uri)


def write_records(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2, shard_bytes: int = 64 << 20) -> DataFrame:
    """Writes docs(doc_id, text) under path, ids of each text then end_id, and returns the index.

    Null texts are empty and give one record of end_id alone; null doc_ids come first; rows that repeat a
    doc_id give a record each, next to one another; an empty table gives no shard and an empty index.
    """
    small_batches(docs.sparkSession)
    spark = docs.sparkSession
    total = docs.select(F.sum(F.octet_length("text"))).first()[0] or 0
    shards = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-total // shard_bytes))

    def run(batches):
        enc = encoder(tokenizer)
        end = np.array([end_id], enc.dtype).tobytes()
        out, name, at, row, lows = None, uuid.uuid4().hex, 0, 0, None
        fs, root = _fs(path)
        for batch in batches:
            for lo, n in row_slices(batch.column(1)):
                ids = batch.column(0).slice(lo, n)
                payloads = [x + end for x in enc.encode([t or "" for t in batch.column(1).slice(lo, n).to_pylist()])]
                if out is None:
                    fs.create_dir(root, recursive=True)
                    out = fs.open_output_stream(f"{root}/_{name}")
                    lows = ids[0].as_py()
                framed = frame(payloads)
                out.write(b"".join(framed))
                sizes = np.array([len(x) for x in framed], np.int64)
                starts = at + np.cumsum(sizes) - sizes
                at += int(sizes.sum())
                yield pa.RecordBatch.from_arrays(
                    [pa.array([f"{name}.rec"] * n), pa.array(np.arange(row, row + n)), ids, pa.array(starts), pa.array(sizes), pa.array((sizes - 16) // enc.dtype.itemsize)],
                    ["shard", "row", "doc_id", "offset", "length", "n_tokens"],
                )
                row += n
        if out is not None:
            out.close()
            fs.move(f"{root}/_{name}", f"{root}/{name}.rec")
        release_memory()

    ranged = docs.select("doc_id", "text").repartitionByRange(shards, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first())
    index = ranged.mapInArrow(run, "shard string, row long, doc_id long, offset long, length long, n_tokens long")
    index.write.parquet(f"{path}/index")
    return read_index(spark, path)


def read_index(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/index")


def read_records(spark: SparkSession, path: str, wide: bool = False, want: DataFrame | None = None) -> DataFrame:
    """Records as (shard, row, doc_id, n_tokens, ids binary as unsigned 32-bit little-endian), checked.

    Each shard is read by the tasks its index rows go to, span after span. want(doc_id) reads only those
    documents, in any order: the index gives their offsets.
    """
    index = read_index(spark, path)
    if want is not None:
        index = index.join(want.select("doc_id").distinct(), "doc_id", "left_semi")
    dtype = np.dtype("<u4" if wide else "<u2")

    def run(batches):
        fs, root = _fs(path)
        held, name = None, None
        for batch in batches:
            rows = batch.to_pydict()
            for lo in range(0, batch.num_rows, 512):
                out = []
                hi = min(lo + 512, batch.num_rows)
                for i in range(lo, hi):
                    if rows["shard"][i] != name:
                        if held is not None:
                            held.close()
                        name = rows["shard"][i]
                        held = fs.open_input_file(f"{root}/{name}")
                    held.seek(rows["offset"][i])
                    out.append(held.read(rows["length"][i]))
                payloads = [x[12:-4] for x in out]
                heads = [x[:8] for x in out]
                sums = np.array([struct.unpack("<II", x[8:12] + x[-4:]) for x in out], np.uint32)
                if (masked(crc32c(heads)) != sums[:, 0]).any() or (masked(crc32c(payloads)) != sums[:, 1]).any() or any(struct.unpack("<Q", h)[0] != len(p) for h, p in zip(heads, payloads)):
                    raise ValueError(f"bad record in {name}")
                ids = [np.frombuffer(p, dtype).astype("<u4").tobytes() for p in payloads]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), batch.column(2).slice(lo, hi - lo), batch.column(5).slice(lo, hi - lo), pa.array(ids, pa.binary())],
                    ["shard", "row", "doc_id", "n_tokens", "ids"],
                )
        if held is not None:
            held.close()

    return index.select("shard", "row", "doc_id", "offset", "length", "n_tokens").mapInArrow(run, "shard string, row long, doc_id long, n_tokens long, ids binary")


def with_starts(records: DataFrame, index: DataFrame) -> DataFrame:
    """Adds start: ids of all records before this one. Shard sums are few; rows meet only inside their shard."""
    sums = index.groupBy("shard").agg(F.sum("n_tokens").alias("_n"), F.min("doc_id").alias("_low"), F.max("doc_id").alias("_high"))
    order = Window.orderBy(F.col("_low").asc_nulls_first(), F.col("_high").asc_nulls_first(), "shard").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.select("shard", F.coalesce(F.sum("_n").over(order), F.lit(0)).alias("_base"))
    inside = Window.partitionBy("shard").orderBy("row").rowsBetween(Window.unboundedPreceding, -1)
    return records.join(base, "shard").withColumn("start", F.col("_base") + F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).drop("_base")


def token_records(docs: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    """Operator 3's query: write, read back, and give (doc_id, start, n_tokens, ids_crc32)."""
    spark = docs.sparkSession
    path = scratch(spark, "records")
    index = write_records(docs, path, tokenizer, end_id)
    back = read_records(spark, path, encoder(tokenizer).wide)

    def sums(batches):
        for b in batches:
            crc = [zlib.crc32(x.as_buffer()) for x in b.column(4)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), b.column(3), pa.array(crc, pa.int64())], ["shard", "row", "doc_id", "n_tokens", "ids_crc32"])

    got = back.mapInArrow(sums, "shard string, row long, doc_id long, n_tokens long, ids_crc32 long")
    return with_starts(got, index).select("doc_id", "start", "n_tokens", "ids_crc32")


def ids_of(record_ids: bytes) -> list[int]:
    return np.frombuffer(record_ids, "<u4").tolist()
