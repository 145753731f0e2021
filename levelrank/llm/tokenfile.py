"""Binary token files: one concatenated id array per segment with Elias-Fano boundaries.

A segment is a byte string: a fixed header, the boundaries' low bits, their high bits in
unary, samples of the positions of set bits for ``select``, and the ids (two or four
bytes each). Boundaries cost about two bits plus log2(mean length) per document and a
``select`` reads one sample, a few words of the high bits and one packed field. Segments are rows of a Parquet
table, so they are written with Spark's commit protocol to any store, in ascending
document order; tables of totals give each segment's global start.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levelrank.llm.bpe import BLOCK_BYTES, JSON_FILE, blocks, json_of_file, pieces_of
from levelrank.llm.common import arrow_rows
from levelrank.plans.staging import shared_path, small_rows

MAGIC, HEADER, SAMPLE = b"EFTOK1\0\0", struct.Struct("<8sQQBBxxxxxxQQ"), 256
END_ID = 2
#: Ids in a segment before it is closed.
SEGMENT_IDS = 2_000_000


# ---------------------------------------------------------------- boundaries
class EliasFano:
    """A non-decreasing sequence below ``limit`` + 1 in near-minimal space."""

    def __init__(self, n: int, low_bits: int, low: np.ndarray, high: np.ndarray, samples: np.ndarray):
        self.n, self.low_bits, self.low, self.high, self.samples = n, low_bits, low, high, samples

    @classmethod
    def build(cls, values: np.ndarray, limit: int) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        bits = max(0, int(limit // max(n, 1)).bit_length() - 1)
        at = (values >> np.uint64(bits)).astype(np.int64) + np.arange(n)
        unary = np.zeros(int((limit >> bits) + n + 1), np.uint8)
        unary[at] = 1
        fields = (values[:, None] >> np.arange(bits, dtype=np.uint64) & np.uint64(1)).astype(np.uint8).ravel()
        return cls(n, bits, np.packbits(fields, bitorder="little"), np.packbits(unary, bitorder="little"), at[::SAMPLE].astype("<u8"))

    def select(self, i: int) -> int:
        """Value ``i``, without unpacking the rest."""
        at, left = int(self.samples[i // SAMPLE]), i % SAMPLE
        byte = at // 8
        word = int(self.high[byte]) >> (at % 8) << (at % 8)
        while (ones := word.bit_count()) <= left:
            left -= ones
            byte += 1
            word = int(self.high[byte])
        for _ in range(left):
            word &= word - 1
        place = byte * 8 + (word & -word).bit_length() - 1
        start = i * self.low_bits
        raw = int.from_bytes(self.low[start // 8 : (start + self.low_bits + 7) // 8].tobytes(), "little")
        return (place - i) << self.low_bits | raw >> start % 8 & (1 << self.low_bits) - 1

    def values(self) -> np.ndarray:
        """All values at once, for scans."""
        place = np.flatnonzero(np.unpackbits(self.high, bitorder="little"))[: self.n]
        high = (place - np.arange(self.n)).astype(np.int64) << self.low_bits
        if not self.low_bits:
            return high
        fields = np.unpackbits(self.low, bitorder="little")[: self.n * self.low_bits].reshape(self.n, self.low_bits)
        return high + fields @ (np.int64(1) << np.arange(self.low_bits, dtype=np.int64))


def pack(docs: list[np.ndarray]) -> bytes:
    """A segment of the documents' ids (each array with its end id)."""
    ids = np.concatenate(docs) if docs else np.zeros(0, "<u4")
    ends = np.cumsum([len(d) for d in docs]) if docs else np.zeros(0, np.int64)
    ef = EliasFano.build(ends, len(ids))
    width = 2 if len(ids) == 0 or ids.max() < 1 << 16 else 4
    head = HEADER.pack(MAGIC, len(docs), len(ids), width, ef.low_bits, len(ef.low), len(ef.high))
    return head + ef.low.tobytes() + ef.high.tobytes() + ef.samples.tobytes() + ids.astype(f"<u{width}").tobytes()


class Segment:
    def __init__(self, raw: bytes):
        magic, self.n_docs, self.n_ids, self.width, low_bits, n_low, n_high = HEADER.unpack_from(raw)
        if magic != MAGIC:
            raise ValueError("not a token segment")
        at = HEADER.size
        low, at = np.frombuffer(raw, np.uint8, n_low, at), at + n_low
        high, at = np.frombuffer(raw, np.uint8, n_high, at), at + n_high
        n_samples = -(-self.n_docs // SAMPLE)
        samples, at = np.frombuffer(raw, "<u8", n_samples, at), at + 8 * n_samples
        self.ends = EliasFano(self.n_docs, low_bits, low, high, samples)
        self.ids = np.frombuffer(raw, f"<u{self.width}", self.n_ids, at)

    def document(self, i: int) -> np.ndarray:
        """Ids of document ``i`` of the segment by two selects."""
        if not 0 <= i < self.n_docs:
            raise IndexError(i)
        return self.ids[self.ends.select(i - 1) if i else 0 : self.ends.select(i)]

    def documents(self) -> Iterator[tuple[int, np.ndarray]]:
        start = 0
        for end in self.ends.values().tolist():
            yield start, self.ids[start:end]
            start = end


# ---------------------------------------------------------------- files
def write_tokens(docs: DataFrame, path: str, spec: str | None = None) -> None:
    """Encode and write: segments of (part, seq, first and last id, doc_ids, n_ids, payload).

    Ascending doc_id, null first; rows with the same doc_id follow by text. Null texts are
    empty documents: their end id alone."""
    spec = spec or json_of_file(public_tokenizers.path(JSON_FILE))
    shared = docs.sparkSession.sparkContext.broadcast(spec)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, pieces = TaskContext.get().partitionId(), pieces_of(shared.value)
        keys, held, n, seq = [], [], 0, 0
        end = np.array([END_ID], "<u4").tobytes()

        def close() -> pa.RecordBatch:
            return pa.record_batch([pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([n], pa.int64()), pa.array([keys], pa.list_(pa.int64())), pa.array([pack(held)], pa.binary())], ["part", "seq", "n_ids", "doc_ids", "payload"])

        for b in batches:
            ids = b.column("doc_id").to_pylist()
            for i, j, body in blocks(b):
                for key, raw in zip(ids[i:j], pieces.batch(body)):
                    held.append(np.frombuffer(b"".join((raw, end)), "<u4"))
                    keys.append(key)
                    n += len(held[-1])
                    if n >= SEGMENT_IDS:
                        yield close()
                        keys, held, n, seq = [], [], 0, seq + 1
        if held:
            yield close()

    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    arrow_rows(ordered, ["doc_id", "text"], run, "part int, seq int, n_ids long, doc_ids array<long>, payload binary", BLOCK_BYTES).write.option("compression", "zstd").parquet(path)


def read_tokens(spark, path: str) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids_crc32, from the files."""
    files = spark.read.schema("part int, seq int, n_ids long, doc_ids array<long>, payload binary").parquet(path)
    totals = small_rows(files.groupBy("part").agg(F.sum("n_ids").alias("n")).orderBy("part"), 1_000_000, "partition totals")
    before, sums = 0, []
    for r in totals:
        sums.append((r.part, before))
        before += r.n
    offsets = spark.createDataFrame(sums, "part int, before long")
    own = F.coalesce(F.sum("n_ids").over(Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = files.select("part", "seq", "n_ids").withColumn("own", own).join(offsets, "part").select("part", "seq", (F.col("own") + F.col("before")).alias("start"))
    placed = files.join(F.broadcast(starts) if len(sums) < 10_000 else starts, ["part", "seq"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for keys, raw, first in zip(b.column("doc_ids"), b.column("payload"), b.column("start").to_pylist()):
                begun, sizes, sums = [], [], []
                for at, ids in Segment(raw.as_py()).documents():
                    begun.append(first + at)
                    sizes.append(len(ids))
                    sums.append(zlib.crc32(ids.astype("<u4").tobytes()))
                yield pa.record_batch([keys.values, pa.array(begun, pa.int64()), pa.array(sizes, pa.int64()), pa.array(sums, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return arrow_rows(placed, ["doc_ids", "payload", "start"], run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_table(docs: DataFrame) -> DataFrame:
    """Write the documents' tokens to the shared folder and read them back."""
    path = shared_path(docs.sparkSession, "tokens")
    write_tokens(docs, path)
    return read_tokens(docs.sparkSession, path)


def export_file(spark, path: str, target: str) -> None:
    """One local file: every segment, prefixed by its length, in global order."""
    rows = spark.read.parquet(path).select("part", "seq", "payload").orderBy("part", "seq").toLocalIterator()
    with open(target, "wb") as f:
        for r in rows:
            f.write(struct.pack("<Q", len(r.payload)))
            f.write(r.payload)
