"""SimHash near-duplicate search.

Fingerprints are bit majorities over shingle hashes, one or more 64-bit lanes wide. ``near_duplicates``
links 64-bit prints within a few bits, exactly, through the Gray-order index of ``grayindex``.

``one_per_group`` works at a resemblance, which takes wide prints and a radius of many bits, where the leading
bits of a Gray order say little. Its upper nodes are masked bit patterns drawn at random: prints that agree
on a mask share a node. Nodes are rows keyed by (mask, pattern), so Spark deals them out; nodes with one
member vanish. Inside a node ``GrayIndex`` sorts members by Gray rank, factors the bits a run of neighbours
shares into inner nodes, and a search adds up differences on its way down, leaving a whole run as soon as the
sum passes the radius. Nodes over ``node_limit`` members are cut in blocks, and every two blocks meet that
still hold unlinked pairs. Nodes hand back a spanning forest of their links, never all pairs; distributed
components finish the job.

Null and empty texts have the all-zero print and link like any other. Repeated rows and ids, ties and
columns of any name: see the two functions.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelrank.llm import grayindex
from levelrank.llm.common import arrow_rows, texts
from levelrank.operators.connect import connected_components
from levelrank.plans.staging import materialise

U64 = np.uint64
#: Members that one inner index takes; larger nodes are searched in blocks.
NODE_LIMIT = 4096
#: Bits of a node that name its mask; shared nodes that may be sent to every task (16 bytes each).
SLOT_BITS, SENT_NODES = 10, 1_000_000
#: Ids stand-ins of groups without any id start here.
NO_ID = 1 << 62


# ---------------------------------------------------------------- fingerprints
def shingle_hashes(text: str, width: int) -> np.ndarray:
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, U64)
    if len(words) < width:
        grams, n = [b" ".join(words)], 1
    else:
        grams, n = map(b" ".join, zip(*(islice(words, i, None) for i in range(width)))), len(words) - width + 1
    return np.fromiter((xxhash.xxh64_intdigest(g, 42) for g in grams), U64, n)


def lanes_of(h: np.ndarray, lanes: int) -> np.ndarray:
    """(n, lanes): the hash itself, then mixes of it that act as further hashes."""
    out = np.empty((len(h), lanes), U64)
    out[:, 0] = h
    for k in range(1, lanes):
        x = h + U64(k * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
        out[:, k] = x ^ (x >> U64(31))
    return out


def bit_majority(rows: np.ndarray) -> np.ndarray:
    """Bits set in over half of the rows, by carry-save adders over whole words."""
    n = len(rows)
    if n == 0:
        return np.zeros(rows.shape[1], U64)
    planes, level = [], rows
    while len(level):
        carries = []
        while len(level) > 2:
            k = len(level) // 3
            a, b, c, rest = level[:k], level[k : 2 * k], level[2 * k : 3 * k], level[3 * k :]
            x = a ^ b
            carries.append((a & b) | (c & x))
            level = np.concatenate([x ^ c, rest]) if len(rest) else x ^ c
        if len(level) == 2:
            carries.append((level[0] & level[1])[None])
            level = (level[0] ^ level[1])[None]
        planes.append(level[0])
        level = np.concatenate(carries) if carries else level[:0]
    need = n // 2 + 1
    if need >> len(planes):
        return np.zeros(rows.shape[1], U64)
    above, equal = np.zeros(rows.shape[1], U64), np.full(rows.shape[1], ~U64(0))
    for k in reversed(range(len(planes))):
        if need >> k & 1:
            equal &= planes[k]
        else:
            above |= equal & planes[k]
            equal &= ~planes[k]
    return above | equal


def fingerprint(text: str | None, width: int = 3, lanes: int = 1) -> np.ndarray:
    return bit_majority(lanes_of(shingle_hashes(text or "", width), lanes))


def fingerprints(docs: DataFrame, width: int = 3, lanes: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp binary): one row per input row; null texts count as empty (all-zero print)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            prints = [fingerprint(t, width, lanes).tobytes() for t in texts(b, text_col)]
            yield pa.record_batch([b.column(id_col), pa.array(prints, pa.binary())], ["id", "fp"])

    return arrow_rows(docs.withColumn(id_col, F.col(id_col).cast("long")), [id_col, text_col], run, "id long, fp binary", 1_000_000)


# ---------------------------------------------------------------- masks
def sampled_masks(lanes: int, bands: int = 144, bits: int = 24) -> list[tuple[int, ...]]:
    """Masks drawn from a wide fingerprint: recall grows with ``bands``, selectivity with ``bits``."""
    rng = np.random.default_rng(7)
    return [tuple(sorted(map(int, rng.choice(64 * lanes, bits, replace=False)))) for _ in range(bands)]


def _mask_words(masks: list[tuple[int, ...]], lanes: int) -> np.ndarray:
    out = np.zeros((len(masks), lanes), U64)
    for i, bits in enumerate(masks):
        for b in bits:
            out[i, b // 64] |= U64(1 << (b % 64))
    return out


def _patterns(fps: np.ndarray, mask: np.ndarray) -> np.ndarray:
    """A 64-bit name of the masked bits; a clash only costs a comparison."""
    x = np.zeros(len(fps), U64)
    for k in range(fps.shape[1]):
        x = (x ^ (fps[:, k] & mask[k])) * U64(0xFF51AFD7ED558CCD)
        x ^= x >> U64(32)
    return x.view(np.int64)


def _prints(column: pa.Array, lanes: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), U64).reshape(-1, lanes)


# ---------------------------------------------------------------- inner index
class GrayIndex:
    """Members in Gray order under a tree of nodes that hold the bits their members share."""

    FAN = 8

    def __init__(self, fps: np.ndarray):
        ranks = grayindex.gray_rank(fps)
        self.order = np.lexsort(tuple(ranks[:, k] for k in reversed(range(fps.shape[1]))))
        value, mask = fps[self.order], np.full_like(fps, ~U64(0))
        self.levels = [[value, mask]]
        while len(value) > self.FAN:
            starts = np.arange(0, len(value), self.FAN)
            first = np.repeat(value[starts], np.diff([*starts, len(value)]), axis=0)
            shared = np.bitwise_and.reduceat(mask & ~(value ^ first), starts, axis=0)
            parent = np.repeat(shared, np.diff([*starts, len(value)]), axis=0)
            self.levels[-1][1] = mask & ~parent  # only what the parent does not hold
            value, mask = value[starts] & shared, shared
            self.levels.append([value, mask])
        self.alive = [np.bincount(np.arange(len(fps)) // self.FAN**k, minlength=len(lv[0])) for k, lv in enumerate(self.levels)]

    def remove(self, at: np.ndarray) -> None:
        for k, left in enumerate(self.alive):
            np.subtract.at(left, at // self.FAN**k, 1)

    def search(self, q: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
        """Places (in Gray order) of living members within the radius, and how far they are."""
        top = len(self.levels) - 1
        at, far = np.arange(len(self.levels[top][0])), None
        for k in range(top, -1, -1):
            if k < top:
                at = (at[:, None] * self.FAN + np.arange(self.FAN)).ravel()
                far = np.repeat(far, self.FAN)
                ok = at < len(self.levels[k][0])
                at, far = at[ok], far[ok]
            live = self.alive[k][at] > 0
            at = at[live]
            value, mask = self.levels[k]
            own = np.bitwise_count((value[at] ^ q) & mask[at]).sum(axis=1, dtype=np.int64)
            far = own if far is None else far[live] + own
            near = far <= radius
            at, far = at[near], far[near]
        return at, far


def forest(fps: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """A spanning forest of the links within the radius: (member, root) positions."""
    n, out = len(fps), []
    if n <= 24:  # a few members: plain comparison
        d = np.bitwise_count(fps[:, None, :] ^ fps[None, :, :]).sum(axis=2, dtype=np.int64) <= radius
        root = list(range(n))
        for i, j in zip(*np.nonzero(np.triu(d, 1))):
            a, b = root[i], root[j]
            if a != b:
                root = [a if r == b else r for r in root]
        return [(i, r) for i, r in enumerate(root) if r != i]
    index = GrayIndex(fps)
    left = np.ones(n, bool)
    sorted_fps = index.levels[0][0]
    for start in range(n):
        if not left[start]:
            continue
        left[start] = False
        index.remove(np.array([start]))
        queue = [start]
        while queue:
            q = queue.pop()
            hit, _ = index.search(sorted_fps[q], radius)
            if len(hit):
                left[hit] = False
                index.remove(hit)
                out += [(int(index.order[h]), int(index.order[start])) for h in hit]
                queue += hit.tolist()
    return out


# ---------------------------------------------------------------- links and components
def _nodes(prints: DataFrame, masks: list[tuple[int, ...]], lanes: int) -> DataFrame:
    """(node, rep): the upper nodes each print belongs to, the mask's number in a node's last bits."""
    words = _mask_words(masks, lanes)
    if len(masks) > 1 << SLOT_BITS:
        raise ValueError("too many masks")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps, reps = _prints(b.column("fp"), lanes), b.column("rep")
            for m in range(len(masks)):
                yield pa.record_batch([pa.array(_patterns(fps, words[m]) << SLOT_BITS | m), reps], ["node", "rep"])

    return arrow_rows(prints, ["rep", "fp"], run, "node long, rep long")


def _forests(groups: DataFrame, lanes: int, radius: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            a, c = [], []
            for members in b.column("members"):
                rows = members.as_py()
                reps = [r["rep"] for r in rows]
                for i, r in forest(np.frombuffer(b"".join(r["fp"] for r in rows), U64).reshape(-1, lanes), radius):
                    a.append(reps[i])
                    c.append(reps[r])
            yield pa.record_batch([pa.array(a, pa.int64()), pa.array(c, pa.int64())], ["a", "b"])

    return groups.select("members").mapInArrow(run, "a long, b long")


def _block_links(large: DataFrame, edges: DataFrame, radius: int, lanes: int, node_limit: int) -> DataFrame:
    """``edges`` and links for all pairs of the (node, rep, fp, n) rows of large nodes.

    Each node is first searched in blocks of about ``node_limit`` members. Members that are
    linked by then need no comparison: a label with many members gets blocks of its own, the
    rest share blocks, and any two blocks meet in one search unless both hold the same label only."""
    members, parts = F.collect_list(F.struct("rep", "fp")).alias("members"), lambda n: F.ceil(F.col(n) / node_limit)
    of_rep = F.xxhash64("rep")
    first = large.groupBy("node", F.pmod(of_rep, parts("n")).alias("block")).agg(members)
    edges = materialise(edges.unionByName(_forests(first, lanes, radius)).distinct(), "links")
    roots = connected_components(edges).select(F.col("id").alias("rep"), "component")
    labelled = materialise(large.join(roots, "rep", "left").select("node", "rep", "fp", F.coalesce("component", "rep").alias("label")), "labelled")
    sizes = labelled.groupBy("node", "label").agg(F.count("*").alias("own")).withColumn("pure", 2 * F.col("own") > node_limit)
    of_node = sizes.groupBy("node").agg(F.count("*").alias("labels"), F.sum(F.when(F.col("pure"), 0).otherwise(F.col("own"))).alias("rest")).where("labels > 1")
    shared = F.pmod(F.xxhash64("label"), F.greatest(parts("rest"), F.lit(1)))
    label = F.when(F.col("pure"), F.col("label"))
    block = F.when(F.col("pure"), F.xxhash64("label", F.pmod(of_rep, parts("own")))).otherwise(shared)
    dealt = materialise(labelled.join(sizes, ["node", "label"]).join(of_node, "node").select("node", "rep", "fp", label.alias("only"), block.alias("block")), "blocks")
    blocks = materialise(dealt.groupBy("node", "block").agg(F.first("only").alias("only")), "pairs")
    a, b = (blocks.select("node", F.col("block").alias(x), F.col("only").alias(f"only_{x}")) for x in "ab")
    pairs = a.join(b, "node").where("a <= b and not (only_a <=> only_b and only_a is not null)").select("node", "a", "b")
    meet = pairs.withColumn("block", F.explode(F.array_distinct(F.array("a", "b"))))
    found = _forests(dealt.join(meet, ["node", "block"]).groupBy("node", "a", "b").agg(members), lanes, radius)
    return edges.unionByName(found)


def links(nodes: DataFrame, masks: list[tuple[int, ...]], radius: int, lanes: int = 1, node_limit: int = NODE_LIMIT) -> DataFrame:
    """(a, b): a spanning forest, per index node, of all pairs of prints within ``radius``.

    ``nodes`` has one row per distinct print: (rep long, fp binary), already written. Nodes
    over ``node_limit`` members go through ``_block_links``, so their size changes the way, not the result."""
    keys = _nodes(nodes, masks, lanes)
    sizes = materialise(keys.groupBy("node").agg(F.count("*").alias("n")).where("n > 1"), "nodes")
    seen = sizes.agg(F.count("*").alias("nodes"), F.max("n").alias("most")).first()
    full = keys.join(F.broadcast(sizes) if seen.nodes <= SENT_NODES else sizes, "node").join(nodes, "rep")
    here = full.where(F.col("n") <= node_limit)
    edges = _forests(here.groupBy("node").agg(F.collect_list(F.struct("rep", "fp")).alias("members")), lanes, radius)
    if (seen.most or 0) > node_limit:
        large = materialise(full.where(F.col("n") > node_limit).select("node", "rep", "fp", "n"), "large")
        edges = _block_links(large, edges, radius, lanes, node_limit)
    return edges.distinct()


def components(prints: DataFrame, radius: int) -> DataFrame:
    """(id, fp) rows -> (id, fp, component): the smallest id reachable over links, and equal
    prints link. Null ids take part but never name a component; a component of null ids
    only is null. An id that several rows carry is one vertex."""
    stand_in = F.lit(NO_ID) + F.pmod(F.xxhash64("fp"), F.lit(NO_ID))
    groups = prints.groupBy("fp").agg(F.min("id").alias("rep"), F.count("*").alias("rows"))
    nodes = materialise(groups.select("fp", F.coalesce("rep", stand_in).alias("rep")), "prints")
    found = grayindex.links(nodes, radius)
    own = prints.where("id is not null").join(nodes, "fp").where("id <> rep").select(F.col("id").alias("a"), F.col("rep").alias("b"))
    repeated = prints.where("id is not null").groupBy("id").agg(F.count("*").alias("n")).where("n > 1").select(F.col("id").alias("a"))
    ties = own.join(repeated, "a", "left_semi")  # the same id under several prints joins them
    roots = connected_components(found.unionByName(ties))
    labelled = nodes.join(roots, nodes.rep == roots.id, "left").select("fp", F.coalesce("component", "rep").alias("component"))
    labelled = labelled.withColumn("component", F.when(F.col("component") < NO_ID, F.col("component")))
    return prints.join(labelled, "fp")


def near_duplicates(docs: DataFrame, radius: int = 2, width: int = 3) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id: exact search over 64-bit prints, one row per row of ``docs``."""
    prints = materialise(fingerprints(docs, width), "simhash")
    out = components(prints, radius)
    return out.select(F.col("id").alias("doc_id"), F.lower(F.hex(_big_endian("fp"))).alias("fingerprint"), F.col("component").alias("component_id"))


def _big_endian(fp: str) -> Column:
    """Bytes of a one-lane print, most significant first."""
    return F.concat(*[F.substring(fp, i, 1) for i in range(8, 0, -1)])


#: Wide prints for the document filter: lanes, shingle width, and the radius at which the
#: angle between two shingle sets stands for a resemblance of 0.8.
WIDE_LANES, WIDE_WORDS, RESEMBLANCE = 8, 5, 0.8


def radius_for(resemblance: float, bits: int) -> int:
    """Differing bits expected at a Jaccard resemblance, from the angle of 0/1 vectors of equal size."""
    cosine = 2 * resemblance / (1 + resemblance)
    return int(np.floor(bits * np.arccos(cosine) / np.pi))


def one_per_group(docs: DataFrame, resemblance: float = RESEMBLANCE) -> DataFrame:
    """``docs`` without near copies: of each group of rows linked at ``resemblance`` or more on five-word
    shingles one stays, that with the smallest doc_id; rows without doc_id come after all others.

    Rows are documents, whatever their doc_id: rows that repeat a doc_id with unrelated texts both stay; of rows
    that repeat doc_id and text one stays. Ties of doc_id go by print, hash of the text, then place in the
    table. Columns are carried unchanged, whatever their names."""
    row, lanes = "row_number", WIDE_LANES
    while row.lower() in {c.lower() for c in docs.columns}:
        row += "_"
    numbered = materialise(docs.withColumn(row, F.monotonically_increasing_id()), "numbered")
    prints = materialise(fingerprints(numbered.select(row, "text"), WIDE_WORDS, lanes, row), "wide")
    nodes = materialise(prints.groupBy("fp").agg(F.min("id").alias("rep")), "prints")
    roots = connected_components(links(nodes, sampled_masks(lanes), radius_for(resemblance, 64 * lanes), lanes))
    groups = nodes.join(roots, nodes.rep == roots.id, "left").select("fp", F.coalesce("component", "rep").alias("component"))
    ids = numbered.select(F.col(row).alias("id"), F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("h"))
    order = F.struct(F.col("doc_id").isNull().alias("without"), "doc_id", "fp", "h", "id")
    rows = materialise(prints.join(groups, "fp").join(ids, "id").select("component", order.alias("order")), "groups")
    kept = rows.groupBy("component").agg(F.min("order").alias("first")).select(F.col("first.id").alias(row))
    gone = rows.select(F.col("order.id").alias(row)).join(kept, row, "left_anti")  # by row number: no group of copies lands in one task
    gone = materialise(gone, "gone")
    few = gone.limit(SENT_NODES + 1).count() <= SENT_NODES
    return numbered.join(F.broadcast(gone) if few else gone, row, "left_anti").select(*docs.columns)
