"""Token files: one concatenated array of ids with Elias-Fano encoded document boundaries.

A segment is one byte string. Layout (little-endian):
  magic 8 bytes | documents u64 | tokens u64 | null ids u64 | id width u8 | low bits u8 | 6 zero bytes |
  lengths of the next four parts, 4 x u64 | document ids | low bits | high bits | select samples u32 | ids.
Boundaries are the token counts up to and with each document. Their low bits stand side by side; the high parts
are a bit vector with a one at (high part + index), so n boundaries below u take about n * (2 + log2(u / n)) bits.
Every SAMPLE-th one's place is kept, so select needs to look at a few words only.

Segments are rows of a Parquet table that Spark's own writer commits: they are readable wherever Spark reads, and
a lost executor leaves no half file. Parts and segments ascend by document id.

Defined cases: a null text is an empty one and has the end id only; null ids come first, in any order; rows of
equal ids stand next to each other; an empty table gives no segments and no rows.
"""

from __future__ import annotations

import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import packing as P
from .common import scratch, spread
from .pieces import encoder

MAGIC, SAMPLE, SEGMENT_TOKENS, END_ID = b"IDSEG001", 256, 1 << 22, 2
#: Offsets of segments are broadcast up to so many (about 32 MB), otherwise joined by shuffle.
MAX_SEGMENTS = 1 << 20


class EliasFano:
    """A non-decreasing sequence of whole numbers."""

    def __init__(self, low_bits: int, low: bytes, high: bytes, samples: np.ndarray, n: int):
        self.low_bits, self.low, self.high, self.samples, self.n = low_bits, low, high, samples, n

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        n = len(values)
        bits = max(int(math.log2(max(int(values[-1]) // n, 1))), 0) if n else 0
        v = values.astype(np.uint64)
        spreadout = (v[:, None] >> np.arange(bits, dtype=np.uint64)) & np.uint64(1)
        ones = (v >> np.uint64(bits)).astype(np.int64) + np.arange(n)
        high = np.zeros(int(ones[-1]) + 1 if n else 0, np.uint8)
        high[ones] = 1
        return cls(bits, np.packbits(spreadout.astype(np.uint8).ravel()).tobytes(), np.packbits(high).tobytes(), ones[::SAMPLE].astype("<u4"), n)

    def _low(self, i: int) -> int:
        a = i * self.low_bits
        word = np.unpackbits(np.frombuffer(self.low, np.uint8)[a // 8 : (a + self.low_bits + 7) // 8 + 1])[a % 8 :][: self.low_bits]
        return int(sum(int(b) << k for k, b in enumerate(word)))

    def select(self, i: int) -> int:
        """The i-th value, from a sample on."""
        at, left = int(self.samples[i // SAMPLE]), i % SAMPLE
        seen, byte = 0, at // 8
        view = np.frombuffer(self.high, np.uint8)
        bits = np.unpackbits(view[byte : byte + 64])
        bits[: at % 8] = 0
        while seen + (count := int(bits.sum())) <= left:
            seen, byte = seen + count, byte + 64
            bits = np.unpackbits(view[byte : byte + 64])
        place = byte * 8 + int(np.flatnonzero(bits)[left - seen])
        return ((place - i) << self.low_bits) | self._low(i)

    def all(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(np.frombuffer(self.high, np.uint8)))[: self.n]
        low = np.zeros(self.n, np.int64)
        if self.low_bits:
            bits = np.unpackbits(np.frombuffer(self.low, np.uint8), count=self.n * self.low_bits).reshape(self.n, -1)
            low = bits.astype(np.int64) @ (1 << np.arange(self.low_bits, dtype=np.int64))
        return ((ones - np.arange(self.n)) << self.low_bits) | low


def write_segment(doc_ids: list[int | None], sizes: np.ndarray, ids: np.ndarray, width: int) -> bytes:
    ef = EliasFano.of(np.cumsum(sizes))
    nulls = sum(d is None for d in doc_ids)
    known = np.array([d for d in doc_ids if d is not None], np.int64)
    docs = P.planes(np.diff(known, prepend=np.int64(0)).view(np.uint64))
    parts = [docs, ef.low, ef.high, ef.samples.tobytes()]
    head = MAGIC + b"".join(int(x).to_bytes(8, "little") for x in (len(sizes), len(ids), nulls)) + bytes([width, ef.low_bits]) + bytes(6)
    return b"".join([head, *(len(p).to_bytes(8, "little") for p in parts), *parts, ids.astype(f"<u{width}").tobytes()])


def read_segment(blob: bytes) -> tuple[list[int | None], EliasFano, np.ndarray]:
    if blob[:8] != MAGIC:
        raise ValueError("not a segment")
    number = lambda at: int.from_bytes(blob[at : at + 8], "little")
    n, tokens, nulls, width, low_bits = number(8), number(16), number(24), blob[32], blob[33]
    at, parts = 72, []
    for k in range(4):
        size = number(40 + 8 * k)
        parts.append(blob[at : at + size])
        at += size
    known = np.cumsum(P.unplaned(parts[0]).view(np.int64))
    ef = EliasFano(low_bits, parts[1], parts[2], np.frombuffer(parts[3], "<u4"), n)
    return [None] * nulls + known.tolist(), ef, np.frombuffer(blob, f"<u{width}", tokens, at)


def write(docs: DataFrame, path: str, tokenizer: str, key: str = "doc_id", text: str = "text", end_id: int = END_ID) -> None:
    """Encodes every text and writes the segments under path, in ascending order of key."""
    plain = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    ordered = plain.repartitionByRange(spread(docs), "doc_id").sortWithinPartitions("doc_id")

    def encode(batches):
        enc, part, seq = encoder(tokenizer), TaskContext.get().partitionId(), 0
        width = 2 if max(enc.size, end_id + 1) <= 1 << 16 else 4
        end = np.array([end_id], "<u4").tobytes()
        held: list = []
        total = 0

        def flush():
            nonlocal seq, total
            ids = np.frombuffer(b"".join(b for _, b in held), "<u4")
            sizes = np.fromiter((len(b) // 4 for _, b in held), np.int64, len(held))
            blob = write_segment([d for d, _ in held], sizes, ids, width)
            row = pa.RecordBatch.from_pylist([{"part": part, "seq": seq, "n_docs": len(held), "n_tokens": len(ids), "blob": blob}], schema=SCHEMA)
            seq, total = seq + 1, 0
            held.clear()
            return row

        for t in batches:
            for d, b in zip(t["doc_id"].to_pylist(), enc.many(t["text"].to_pylist()), strict=True):
                held.append((d, b + end))
                total += len(b) // 4 + 1
                if total >= SEGMENT_TOKENS:
                    yield flush()
        if held:
            yield flush()

    ordered.mapInArrow(encode, "part int, seq int, n_docs long, n_tokens long, blob binary").write.option("compression", "uncompressed").parquet(path)


SCHEMA = pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("blob", pa.binary())])


def read(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """One row for each document of the files: doc_id, start, n_tokens, ids_crc32, and with with_ids its ids."""
    files = spark.read.parquet(path)
    # one small row for each segment of some millions of ids, summed up in one task
    order = Window.orderBy("part", "seq").rowsBetween(Window.unboundedPreceding, -1)
    starts = files.select("part", "seq", F.coalesce(F.sum("n_tokens").over(order), F.lit(0)).alias("base"))
    starts = F.broadcast(starts) if files.count() <= MAX_SEGMENTS else starts
    kinds = [("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())] + [("ids", pa.list_(pa.int32()))] * with_ids

    def decode(batches):
        for t in batches:
            for blob, base in zip(t["blob"], t["base"].to_pylist(), strict=True):
                docs, ef, ids = read_segment(blob.as_py())
                ends = ef.all()
                begin, wide = np.concatenate([[0], ends[:-1]]), ids.astype("<u4")
                crc = [zlib.crc32(wide[a:b]) for a, b in zip(begin, ends, strict=True)]
                cols = [pa.array(docs, pa.int64()), pa.array(begin + base), pa.array(ends - begin), pa.array(crc, pa.int64())]
                if with_ids:
                    cols.append(pa.array([wide[a:b].astype(np.int32) for a, b in zip(begin, ends, strict=True)], pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, [x for x, _ in kinds])

    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<int>" * with_ids
    return files.select("part", "seq", "blob").join(starts, ["part", "seq"]).select("blob", "base").mapInArrow(decode, schema)


def fetch(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """The ids of some documents (doc_id, ids): select gives the two ends, nothing else is decoded."""
    wanted = np.unique(np.array(doc_ids, np.int64))

    def pick(batches):
        for t in batches:
            rows = []
            for blob in t["blob"]:
                docs, ef, ids = read_segment(blob.as_py())
                nulls = sum(d is None for d in docs)
                known = np.array(docs[nulls:], np.int64)
                for i in np.flatnonzero(np.isin(known, wanted)) + nulls:
                    a, b = ef.select(int(i) - 1) if i else 0, ef.select(int(i))
                    rows.append({"doc_id": docs[i], "ids": ids[a:b].astype(np.int32).tolist()})
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32()))]))

    return spark.read.parquet(path).select("blob").mapInArrow(pick, "doc_id long, ids array<int>")


def round_trip(docs: DataFrame, tokenizer: str) -> DataFrame:
    path = scratch(docs.sparkSession, "ids")
    write(docs, path, tokenizer)
    return read(docs.sparkSession, path)
