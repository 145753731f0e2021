"""Line dedup over levelled sorted runs of line hashes.

A run is a written table of (h1, h2, n): 128-bit line keys in sorted order with the number
of documents that hold them. The table is read once: its documents are dealt to ``BATCHES`` batches by
their hash and each batch's keys are counted. Batch by batch, keys that the runs already know as settled
(found in ``min_docs`` documents) are left out by a merge anti join, and the rest becomes a run of
level 0. When a level has ``fan_in`` runs they are merged into one run of the next level, so n batches
leave about fan_in * log(n) runs.

Null and empty texts are one empty line, whose key is empty and never dropped. Repeated rows are documents of
their own. Lines of very long texts are hashed one by one, texts are never cut. Other columns are
carried, whatever their names; the numbers that a join needs take free names.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelrank.llm.common import arrow_rows, mapped, texts
from levelrank.plans.staging import materialise, shared_path

MIN_DOCS, FAN_IN, BATCHES = 10, 4, 8
#: Keys that may be sent to every task (16 bytes each); above it lines are joined by key.
SENT_KEYS = 2_000_000
#: Keys a task counts before handing them on.
FLUSH = 200_000


def key_of(line: bytes) -> bytes:
    """128-bit hash of a line, stripped and lower-cased in ASCII; empty keys give b''."""
    k = line.strip().lower()
    return xxhash.xxh3_128_digest(k) if k else b""


def _pairs(keys: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(keys), "<i8").reshape(-1, 2)


def count_lines(docs: DataFrame, batches: int = 1) -> DataFrame:
    """(batch, h1, h2, n): documents per line key and batch, summed within tasks first."""

    def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[Counter] = [Counter() for _ in range(batches)]

        def out() -> Iterator[pa.RecordBatch]:
            for k, counts in enumerate(held):
                if counts:
                    h = _pairs(list(counts))
                    yield pa.record_batch([pa.array(np.full(len(h), k, np.int32)), pa.array(h[:, 0]), pa.array(h[:, 1]), pa.array(list(counts.values()), pa.int64())], ["batch", "h1", "h2", "n"])
                    counts.clear()

        for b in parts:
            for k, t in zip(b.column("batch").to_pylist(), texts(b)):
                held[k].update({x for x in map(key_of, t.encode("utf-8", "surrogatepass").split(b"\n")) if x})
                if len(held[k]) > FLUSH // batches:
                    yield from out()
        yield from out()

    dealt = docs.select("text", F.pmod(F.xxhash64("text"), F.lit(batches)).cast("int").alias("batch"))
    return arrow_rows(dealt, ["text", "batch"], run, "batch int, h1 long, h2 long, n long").groupBy("batch", "h1", "h2").agg(F.sum("n").alias("n"))


class LineRuns:
    """The levelled runs. ``add`` takes a batch's counted keys (h1, h2, n); ``frequent`` lists the settled keys."""

    def __init__(self, spark: SparkSession, min_docs: int = MIN_DOCS, fan_in: int = FAN_IN):
        self.spark, self.min_docs, self.fan_in = spark, min_docs, fan_in
        self.levels: list[list[DataFrame]] = []
        self.compacted = 0

    def _merged(self, runs: list[DataFrame]) -> DataFrame:
        all_runs = runs[0]
        for r in runs[1:]:
            all_runs = all_runs.unionByName(r)
        return all_runs if len(runs) == 1 else all_runs.groupBy("h1", "h2").agg(F.sum("n").alias("n"))

    def _write(self, run: DataFrame, level: int) -> DataFrame:
        return materialise(run.sortWithinPartitions("h1", "h2"), f"run{level}")

    def runs(self) -> list[DataFrame]:
        return [r for level in self.levels for r in level]

    def add(self, fresh: DataFrame) -> None:
        for known in self.runs():
            settled = known.where(F.col("n") >= self.min_docs)
            fresh = fresh.join(settled.select("h1", "h2").hint("merge"), ["h1", "h2"], "left_anti")
        level = 0
        run = self._write(fresh, level)
        while True:
            if len(self.levels) <= level:
                self.levels.append([])
            self.levels[level].append(run)
            if len(self.levels[level]) < self.fan_in:
                return
            run = self._write(self._merged(self.levels[level]), level + 1)
            self.levels[level] = []
            self.compacted += 1
            level += 1

    def frequent(self) -> DataFrame:
        runs = self.runs()
        if not runs:
            return self.spark.createDataFrame([], "h1 long, h2 long")
        return self._merged(runs).where(F.col("n") >= self.min_docs).select("h1", "h2")


def _kept(text: str, drop: set[bytes]) -> tuple[int, int, bytes]:
    lines = text.encode("utf-8", "surrogatepass").split(b"\n")
    keep = [x for x in lines if key_of(x) not in drop]
    return len(lines), len(lines) - len(keep), b"\n".join(keep)


def _dropped_places(docs: DataFrame, frequent: DataFrame) -> DataFrame:
    """(row, places): which lines of each row go, by a join on the keys; for key sets of any size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, places, keys = [], [], []
            for row, t in zip(b.column("row").to_pylist(), texts(b)):
                for i, x in enumerate(t.encode("utf-8", "surrogatepass").split(b"\n")):
                    if k := key_of(x):
                        rows.append(row)
                        places.append(i)
                        keys.append(k)
            h = _pairs(keys)
            yield pa.record_batch([pa.array(rows, pa.int64()), pa.array(places, pa.int32()), pa.array(h[:, 0]), pa.array(h[:, 1])], ["row", "place", "h1", "h2"])

    lines = arrow_rows(docs, ["row", "text"], run, "row long, place int, h1 long, h2 long")
    return lines.join(frequent, ["h1", "h2"], "left_semi").groupBy("row").agg(F.collect_list("place").alias("places"))


def line_runs(docs: DataFrame, min_docs: int = MIN_DOCS, batches: int = BATCHES) -> LineRuns:
    """The runs of a whole table: its lines are counted in one pass and added batch by batch."""
    spark = docs.sparkSession
    path = shared_path(spark, "counted")
    count_lines(docs, batches).write.partitionBy("batch").parquet(path)
    counted, runs = spark.read.schema("h1 long, h2 long, n long, batch int").parquet(path), LineRuns(spark, min_docs)
    for k in range(batches):
        runs.add(counted.where(F.col("batch") == k).select("h1", "h2", "n"))
    return runs


def settled_keys(docs: DataFrame, min_docs: int = MIN_DOCS, batches: int = BATCHES) -> DataFrame:
    """Keys found in ``min_docs`` documents of the whole table."""
    return materialise(line_runs(docs, min_docs, batches).frequent(), "frequent")


def _free(name: str, columns: list[str]) -> str:
    while name in {c.lower() for c in columns}:
        name += "_"
    return name


def _apply(docs: DataFrame, frequent: DataFrame, columns: list[str], make, schema) -> DataFrame:
    """Run ``make(batches, drop_of)`` where drop_of(batch) gives each row's (n_lines, n_dropped, kept)."""
    small = frequent.limit(SENT_KEYS + 1).count() <= SENT_KEYS
    if small:
        got = frequent.toArrow()
        raw = np.stack([got["h1"].to_numpy(), got["h2"].to_numpy()], axis=1).astype("<i8").tobytes() if got.num_rows else b""
        shared = docs.sparkSession.sparkContext.broadcast(raw)

        def sent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            drop = {shared.value[i : i + 16] for i in range(0, len(shared.value), 16)}
            for b in batches:
                yield make(b, [_kept(t, drop) for t in texts(b)])

        return mapped(docs.select(*columns), sent, schema)
    row, lines_gone = _free("row", docs.columns), _free("places", docs.columns)
    numbered = materialise(docs.withColumn(row, F.monotonically_increasing_id()), "numbered")
    gone_of = _dropped_places(numbered.select(F.col(row).alias("row"), "text"), frequent).select(F.col("row").alias(row), F.col("places").alias(lines_gone))
    placed = numbered.join(gone_of, row, "left")

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for t, places in zip(texts(b), b.column(lines_gone).to_pylist()):
                lines, gone = t.encode("utf-8", "surrogatepass").split(b"\n"), set(places or ())
                out.append((len(lines), len(gone), b"\n".join(x for i, x in enumerate(lines) if i not in gone)))
            yield make(b, out)

    return mapped(placed.select(*columns, lines_gone), joined, schema)


def line_report(docs: DataFrame, min_docs: int = MIN_DOCS) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256. Null or empty texts are one empty line, which stays."""

    def make(b: pa.RecordBatch, rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
        return pa.record_batch([b.column("doc_id"), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([hashlib.sha256(r[2]).hexdigest() for r in rows], pa.string())], ["doc_id", "n_lines", "n_dropped", "kept_sha256"])

    docs = docs.withColumn("doc_id", F.col("doc_id").cast("long"))
    return _apply(docs, settled_keys(docs, min_docs), ["doc_id", "text"], make, "doc_id long, n_lines long, n_dropped long, kept_sha256 string")


def drop_frequent_lines(docs: DataFrame, min_docs: int = MIN_DOCS) -> DataFrame:
    """``docs`` with frequent lines cut from the texts; n_chars, where present, follows. Null texts stay null."""
    names, schema = docs.columns, docs.schema

    def make(b: pa.RecordBatch, rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
        old = b.column("text").to_pylist()
        new = [None if o is None else r[2].decode("utf-8", "surrogatepass") for o, r in zip(old, rows)]
        columns = [b.column(c) for c in names]
        columns[names.index("text")] = pa.array(new, pa.string())
        return pa.record_batch(columns, names)

    out = _apply(docs, settled_keys(docs, min_docs), names, make, schema)
    if "n_chars" in names:
        out = out.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text")).otherwise(F.col("n_chars")).cast(schema["n_chars"].dataType))
    return out
