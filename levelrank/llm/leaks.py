"""Benchmark decontamination: q-gram lemma filter in diagonal bands, banded verification.

Texts and benchmark items are compared in normal form: lower case, words joined by one
blank. An item leaks into a text if a stretch of it, ``STRETCH`` characters or the whole
item where that is shorter, stands in the text within an edit budget of ``RATE``. By the
q-gram lemma such a stretch shares at least length - q + 1 - q * edits q-grams with the text, all
on diagonals that lie at most the edits apart. So the text's q-grams look up the items', hits are
counted in overlapping bands of diagonals, and each stretch of an item that reaches the bound in a
band is aligned with the text there, wherever its copy starts and ends.

Items go to the tasks in blocks of bounded size; each block meets every text.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.llm.common import arrow_rows, mapped, texts

Q, STRETCH, RATE = 10, 80, 0.05
#: Characters of items that one block may hold.
BLOCK_CHARS = 4_000_000
#: Characters of text that are searched at a time; pairs of equal q-grams in text and items above which a slice is halved.
SLICE, PAIRS = 2_000_000, 4_000_000
BREAK = re.compile(r"[\W_]+")
MIX = np.uint64(0x9E3779B97F4A7C15)
TABLE_BITS = 22


def normal(text: str | None) -> str:
    return BREAK.sub(" ", (text or "").lower()).strip()


def grams(codes: np.ndarray) -> np.ndarray:
    """Rolling 64-bit hash of every Q characters."""
    n = len(codes) - Q + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = codes[:n].astype(np.uint64)
    for i in range(1, Q):
        h *= MIX
        h += codes[i : i + n]
    return h ^ (h >> np.uint64(29))


def codes_of(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def banded_distance(a: str, b: str, most: int) -> int:
    """Edit distance if at most ``most``, else most + 1; work is length times band."""
    if a == b:
        return 0
    if abs(len(a) - len(b)) > most:
        return most + 1
    big = most + 1
    row = [j if j <= most else big for j in range(len(b) + 1)]
    for i, x in enumerate(a, 1):
        lo, hi = max(1, i - most), min(len(b), i + most)
        new = [big] * (len(b) + 1)
        new[0] = i if i <= most else big
        for j in range(lo, hi + 1):
            new[j] = min(row[j] + 1, new[j - 1] + 1, row[j - 1] + (x != b[j - 1]), big)
        row = new
        if min(row[max(0, lo - 1) : hi + 1]) > most:
            return big
    return row[len(b)]


def nearest(piece: str, text: str, most: int) -> tuple[int, int, int] | None:
    """(start, end, edits) of the stretch of ``text``, of any length, that is nearest to ``piece``, if
    within ``most`` edits. Bits of whole numbers hold a column of the alignment, whose text ends are free."""
    if (at := text.find(piece)) >= 0:
        return at, at + len(piece), 0
    places: dict[str, int] = {}
    for i, c in enumerate(piece):
        places[c] = places.get(c, 0) | 1 << i
    whole, top = (1 << len(piece)) - 1, 1 << (len(piece) - 1)
    more, less, far, best, end = whole, 0, len(piece), most + 1, 0
    for j, c in enumerate(text, 1):
        same = places.get(c, 0)
        flat = (((same & more) + more) ^ more) | same | less
        up, down = less | ~(flat | more), flat & more
        far += bool(up & top) - bool(down & top)
        up, down = up << 1, down << 1
        more, less = (down | ~(flat | up)) & whole, up & flat & whole
        if far < best:
            best, end = far, j
    if best > most:
        return None
    n = len(piece)
    for start in sorted(range(max(0, end - n - best), max(0, end - n + best) + 1), key=lambda x: abs(end - n - x)):
        if banded_distance(piece, text[start:end], best) <= best:
            return start, end, best


class Items:
    """A block of items: sorted q-gram hashes with their places, and a bit table before them."""

    def __init__(self, rows: list[tuple[int, str]]):
        self.ids = [i for i, _ in rows]
        self.texts = [t for _, t in rows]
        self.length = np.array([len(t) for t in self.texts] or [0])
        self.stretch = np.minimum(self.length, STRETCH)
        self.budget = np.floor(self.stretch * RATE).astype(int)
        while (short := (self.stretch - Q + 1 - Q * self.budget < 1) & (self.budget > 0)).any():
            self.budget[short] -= 1
        self.need = self.stretch - Q + 1 - Q * self.budget
        h, item, place = [], [], []
        for k, t in enumerate(self.texts):
            g = grams(codes_of(t))
            h.append(g)
            item.append(np.full(len(g), k))
            place.append(np.arange(len(g)))
        h = np.concatenate(h) if h else np.zeros(0, np.uint64)
        order = np.argsort(h, kind="stable")
        self.h = h[order]
        self.item = np.concatenate(item)[order] if item else np.zeros(0, int)
        self.place = np.concatenate(place)[order] if place else np.zeros(0, int)
        self.table = np.zeros(1 << TABLE_BITS, bool)
        self.table[self.h >> np.uint64(64 - TABLE_BITS)] = True

    def find(self, text: str, first: bool = False) -> dict[int, tuple[int, int, int]]:
        """item number -> (start, end, edits) in the normal form; the longest stretch wins. ``first`` stops at
        any leak. Slices of the text overlap by the longest copy of a stretch, so each copy lies whole in one; a slice
        whose q-grams meet too many of the items' is halved, so memory does not follow the product of repeats."""
        found: dict[int, tuple[int, int, int]] = {}
        if not len(self.h):
            return found
        codes, reach = codes_of(text), int((self.stretch + self.budget).max())
        todo = [(s, min(len(codes), s + SLICE + reach)) for s in range(0, len(codes), SLICE)][::-1]
        while todo and not (first and found):
            lo, hi = todo.pop()
            g = grams(codes[lo:hi])
            at = np.flatnonzero(self.table[g >> np.uint64(64 - TABLE_BITS)])
            if not len(at):
                continue
            start, end = np.searchsorted(self.h, g[at]), np.searchsorted(self.h, g[at], "right")
            n = end - start
            if n.sum() > PAIRS and hi - lo > 4 * reach:
                mid = (lo + hi) // 2
                todo += [(mid, hi), (lo, mid + reach)]
            elif n.any():
                self._slice(text, np.repeat(at + lo, n), np.repeat(start, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n), found, first)
        return found

    def _slice(self, text: str, pos: np.ndarray, own: np.ndarray, found: dict, first: bool) -> None:
        """Leaks among pairs of equal q-grams: places in the text, and rows of the sorted table."""
        item, place = self.item[own], self.place[own]
        enough = np.bincount(item, minlength=len(self.ids)) >= self.need
        keep = enough[item]
        pos, item, place = pos[keep], item[keep], place[keep]
        if not len(pos):
            return
        diagonal = pos - place + int(self.length.max())
        width = 2 * int(self.budget.max()) + 2
        for shift in (0, width // 2):  # overlapping bands: any budget of diagonals fits one of them
            band = (diagonal + shift) // width
            order = np.lexsort((pos, band, item))
            b, i, p, q = band[order], item[order], pos[order], place[order]
            edges = np.flatnonzero(np.r_[True, (b[1:] != b[:-1]) | (i[1:] != i[:-1])])
            ends = np.r_[edges[1:], len(b)]
            full = ends - edges >= self.need[i[edges]]
            for x, y in zip(edges[full], ends[full]):
                self._band(text, int(i[x]), p[x:y], q[x:y], found)
                if first and found:
                    return

    def _band(self, text: str, k: int, p: np.ndarray, q: np.ndarray, found: dict) -> None:
        """Every stretch of item ``k`` that has enough of its q-grams in the band is aligned, unless a leak found here holds it."""
        item, need, stretch, budget = self.texts[k], int(self.need[k]), int(self.stretch[k]), int(self.budget[k])
        have = np.zeros(len(item) - Q + 1, int)
        have[q] = 1
        upto = np.r_[0, np.cumsum(have)]
        starts = np.flatnonzero(upto[stretch - Q + 1 :] - upto[: len(item) - stretch + 1] >= need)
        diagonal = p - q
        first, last = int(diagonal.min()) - budget, int(diagonal.max()) + budget
        held = (0, -1)
        for a in starts.tolist():
            if held[0] <= a and a + stretch <= held[1]:
                continue
            lo = max(0, a + first)
            got = nearest(item[a : a + stretch], text[lo : max(lo, a + stretch + last)], budget)
            if got:
                *hit, held = self._grow(text, item, lo + got[0], lo + got[1], a, stretch, got[2])
                if k not in found or hit[1] - hit[0] > found[k][1] - found[k][0]:
                    found[k] = tuple(hit)

    @staticmethod
    def _grow(text: str, item: str, lo: int, hi: int, a: int, n: int, edits: int) -> tuple[int, int, int, tuple[int, int]]:
        b = a + n
        while lo > 0 and a > 0 and text[lo - 1] == item[a - 1]:
            lo, a = lo - 1, a - 1
        while hi < len(text) and b < len(item) and text[hi] == item[b]:
            hi, b = hi + 1, b + 1
        return lo, hi, edits, (a, b)


def item_blocks(benchmark: DataFrame) -> Iterator[list[tuple[int, str]]]:
    """The items in normal form, in blocks of at most about ``BLOCK_CHARS`` characters each.
    Null ids and items under ``Q`` characters are left out."""
    items = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text")
    total = items.agg(F.sum(F.length("text"))).first()[0] or 0
    n = int(total // BLOCK_CHARS) + 1
    for k in range(n):
        part = items if n == 1 else items.where(F.pmod(F.xxhash64("item_id"), F.lit(n)) == k)
        rows = [(r.item_id, normal(r.text)) for r in part.toLocalIterator()]
        yield [r for r in rows if len(r[1]) >= Q]


def find_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, start, end (characters of the text's normal form), edits: a row per text and leaked item."""
    spark, out = docs.sparkSession, None
    for rows in item_blocks(benchmark):
        shared = spark.sparkContext.broadcast(Items(rows))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            items = shared.value
            for b in batches:
                rows = [(i, items.ids[k], *hit) for i, t in zip(b.column("doc_id").to_pylist(), texts(b)) for k, hit in items.find(normal(t)).items()]
                yield pa.record_batch([pa.array([r[c] for r in rows], pa.int64()) for c in range(5)], ["doc_id", "item_id", "start", "end", "edits"])

        part = arrow_rows(docs, ["doc_id", "text"], run, "doc_id long, item_id long, start long, end long, edits long")
        out = part if out is None else out.unionByName(part)
    return out


def drop_leaking(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents that hold no stretch of any item; all columns unchanged. One pass per block of items."""
    for rows in item_blocks(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(Items(rows))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            items = shared.value
            for b in batches:
                yield b.filter(pa.array([not items.find(normal(t), True) for t in texts(b)], pa.bool_()))

        docs = mapped(docs, run, docs.schema)
    return docs
