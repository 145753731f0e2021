"""A Gray-order hierarchical index over 64-bit fingerprints, for all links within a radius.

Distinct prints are sorted by Gray rank into blocks of bounded size (range partitions). Prints that follow each
other in Gray order differ in few bits, so the members of a block share many bits, and these are
factored out, storey by storey:

* the root table has one row per block, the bits its members share; it has ``N / BLOCK`` rows and is broadcast;
* in a block a tree of nodes, eight members or nodes each, holds what their members share beyond the
  parent's bits, down to the members themselves.

A print's search starts at the root table and adds up differences on its way down; it leaves a block or a node with
all it holds as soon as the sum passes the radius. Nothing else is compared: every link comes from
such a search. Links run both ways, so a print visits only blocks from its own on. Within a block all members
are searched and joined into trees (a spanning forest); visitors from other blocks hand back one link per
tree that they meet. A print has at most 2,081 prints within two bits, so no search grows with a group. Visitors of a block are dealt to as many tasks
as their number asks for, each with a copy of the block's members.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.plans.staging import materialise, small_rows

U64 = np.uint64
#: Members of a block, rows of the root table, visitors of a block that one task takes.
BLOCK, MAX_BLOCKS, VISITORS = 100_000, 2_000_000, 1_000_000
FAN = 8
#: Pairs of searches and nodes that are looked at in one step.
STEP = 4_000_000


def gray_rank(prints: np.ndarray) -> np.ndarray:
    """The place of each print in Gray order: neighbours in it differ in one bit."""
    x = prints.copy()
    for s in (1, 2, 4, 8, 16, 32):
        x ^= x >> U64(s)
    return x


class GrayTree:
    """Members in Gray order under storeys of nodes that hold the bits their members share."""

    def __init__(self, prints: np.ndarray):
        self.order = np.argsort(gray_rank(prints), kind="stable")
        value, mask = prints[self.order], np.full(len(prints), ~U64(0))
        self.members, self.storeys, self.visited = value, [[value, mask]], 0
        while len(value) > FAN:
            starts = np.arange(0, len(value), FAN)
            sizes = np.diff([*starts, len(value)])
            shared = np.bitwise_and.reduceat(mask & ~(value ^ np.repeat(value[starts], sizes)), starts)
            self.storeys[-1][1] = mask & ~np.repeat(shared, sizes)  # only what the parent does not hold
            value, mask = value[starts] & shared, shared
            self.storeys.append([value, mask])

    def search(self, queries: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, place in Gray order, distance) of all members within the radius, by one descent of all queries."""
        top = len(self.storeys) - 1
        roots = len(self.storeys[top][0])
        if len(queries) * roots > STEP and len(queries) > 1:
            half = max(1, STEP // roots)
            parts = [self.search(queries[k : k + half], radius) for k in range(0, len(queries), half)]
            return np.concatenate([p[0] + k * half for k, p in enumerate(parts)]), *(np.concatenate([p[i] for p in parts]) for i in (1, 2))
        q, at = np.repeat(np.arange(len(queries), dtype=np.int32), roots), np.tile(np.arange(roots, dtype=np.int32), len(queries))
        return self._descend(queries, q, at, np.zeros(len(q), np.uint8), top, radius)

    def _descend(self, queries, q, at, far, k, radius):
        if len(q) > STEP:
            cut = [slice(i, i + STEP // 2) for i in range(0, len(q), STEP // 2)]
            parts = [self._descend(queries, q[c], at[c], far[c], k, radius) for c in cut]
            return tuple(np.concatenate([p[i] for p in parts]) for i in range(3))
        value, mask = self.storeys[k]
        self.visited += len(q)
        far = far + np.bitwise_count((value[at] ^ queries[q]) & mask[at])
        near = far <= radius
        q, at, far = q[near], at[near], far[near]
        if k == 0:
            return q, at, far
        at = (at[:, None] * np.int32(FAN) + np.arange(FAN, dtype=np.int32)).ravel()
        real = at < len(self.storeys[k - 1][0])
        return self._descend(queries, np.repeat(q, FAN)[real], at[real], np.repeat(far, FAN)[real], k - 1, radius)

    def forest(self, radius: int, each: int = 4096) -> np.ndarray:
        """The smallest place that each member is linked to inside the block, over any number of links."""
        root = np.arange(len(self.members))
        for k in range(0, len(root), each):
            q, at, _ = self.search(self.members[k : k + each], radius)
            root = merged(root, q + k, at)
        return root


def merged(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """``root`` after joining the trees of ``a`` and ``b``: smallest places spread along links and pointers until none moves."""
    while True:
        x, y = root[a], root[b]
        if (x == y).all():
            return root
        root = root.copy()
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]


def _signed(prints: np.ndarray) -> np.ndarray:
    """Unsigned order as signed numbers."""
    return (prints ^ U64(1 << 63)).view(np.int64)


def _blocks(nodes: DataFrame, block: int) -> DataFrame:
    """(rep, print long, block): distinct prints, range-partitioned by Gray rank, written."""

    def rank(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            prints = np.frombuffer(b"".join(b.column("fp").to_pylist()), U64)
            yield pa.record_batch([b.column("rep"), pa.array(prints.view(np.int64)), pa.array(_signed(gray_rank(prints)))], ["rep", "print", "rank"])

    ranked = materialise(nodes.select("rep", "fp").mapInArrow(rank, "rep long, print long, rank long"), "ranked")
    parts = max(1, -(-ranked.count() // block))
    return materialise(ranked.repartitionByRange(parts, "rank").withColumn("block", F.spark_partition_id()).drop("rank"), "blocks")


def links(nodes: DataFrame, radius: int, block: int = BLOCK, visitors: int = VISITORS) -> DataFrame:
    """(a, b): links between ``rep`` of distinct prints (rep long, fp binary of 8 bytes) within ``radius`` bits that hold
    together whatever all such links hold together."""
    spark = nodes.sparkSession
    dealt = _blocks(nodes, block)
    shared = dealt.groupBy("block").agg(F.bit_and("print").alias("ones"), F.bit_or("print").alias("any"))
    rows = small_rows(shared.orderBy("block"), MAX_BLOCKS, "root table")
    value = np.array([r.ones for r in rows], np.int64).view(U64)
    mask = ~(value ^ np.array([r["any"] for r in rows], np.int64).view(U64))
    number = np.array([r.block for r in rows], np.int64)
    root = spark.sparkContext.broadcast((value, mask, number))

    def visits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        value, mask, number = root.value
        step = max(1, STEP // max(1, len(value)))
        for b in batches:
            for k in range(0, len(b), step):
                part = b.slice(k, step)
                prints = part.column("print").to_numpy().view(U64)
                far = np.bitwise_count((prints[:, None] ^ value) & mask)
                q, at = np.nonzero((far <= radius) & (number > part.column("block").to_numpy()[:, None]))
                yield pa.record_batch([pa.array(number[at], pa.int32()), part.column("rep").take(pa.array(q)), part.column("print").take(pa.array(q))], ["block", "rep", "print"])

    came = materialise(dealt.select("rep", "print", "block").mapInArrow(visits, "block int, rep long, print long"), "visits")
    shares = came.groupBy("block").agg(F.ceil(F.count("*") / visitors).cast("int").alias("shares"))
    salt = lambda n: F.pmod(F.xxhash64("rep"), n).cast("int")
    asked = came.join(F.broadcast(shares), "block").select("block", salt(F.col("shares")).alias("share"), F.lit(1).alias("role"), "rep", "print")
    held = dealt.join(F.broadcast(shares), "block", "left").select("block", F.explode(F.sequence(F.lit(0), F.coalesce("shares", F.lit(1)) - 1)).alias("share"), F.lit(0).alias("role"), "rep", "print")
    tasks = held.unionByName(asked).repartition("block", "share").sortWithinPartitions("block", "share", "role", "print")

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, reps, held, tree, top = None, [], [], None, None

        def grow() -> Iterator[pa.RecordBatch]:
            nonlocal tree, top, reps
            tree = GrayTree(np.concatenate(held))
            names = np.concatenate(reps)[tree.order]
            top = names[tree.forest(radius)]
            reps = [names]
            if own[1] == 0:
                linked = top != names
                yield pa.record_batch([pa.array(names[linked]), pa.array(top[linked])], ["a", "b"])

        for b in batches:
            keys = np.stack([b.column(c).to_numpy() for c in ("block", "share", "role")], axis=1)
            edges = np.flatnonzero(np.r_[True, (keys[1:] != keys[:-1]).any(axis=1)]) if len(keys) else []
            for x, z in zip(edges, [*edges[1:], len(keys)]):
                key, role = (int(keys[x, 0]), int(keys[x, 1])), keys[x, 2]
                rep, prints = b.column("rep").to_numpy()[x:z], b.column("print").to_numpy()[x:z].view(U64)
                if key != own:
                    if own is not None and tree is None:
                        yield from grow()
                    own, reps, held, tree = key, [], [], None
                if role == 0:
                    reps.append(rep)
                    held.append(prints)
                    continue
                if tree is None:
                    yield from grow()
                q, at, _ = tree.search(prints, radius)
                met = np.unique(np.stack([rep[q], top[at]], axis=1), axis=0)  # one link per tree that a visitor meets
                yield pa.record_batch([pa.array(met[:, 0]), pa.array(met[:, 1])], ["a", "b"])
        if own is not None and tree is None:
            yield from grow()

    return tasks.mapInArrow(answer, "a long, b long").distinct()
