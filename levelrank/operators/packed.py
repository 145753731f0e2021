"""Ranks and edge visits of graphs whose vertices fit arrays of the driver, while their edges stay in packed blocks.

Edges are numbered and dealt once by ranges of targets, a block of sorted edges a row of a written table: four bytes an edge and eight
a target (eight an edge more where probabilities differ inside a source). A pass sends arrays over the vertices to all tasks, each of which goes
over its blocks and gives back what came to its targets. Components, levels and the rounds of every method are made
of such passes; components that a task's kernel takes are gathered there, and a sum whose packed edges one task can hold goes all its
rounds in that task. Nothing is stopped early or estimated: rounds are those of the kernels, but for the order in which doubles are added.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.functions import kernels as K
from levelrank.operators.model import LOCAL_EDGES, Graph
from levelrank.plans.staging import materialise

#: Vertices whose arrays are sent to all tasks (8 bytes each); edges of a block, and those a packing task holds at a time.
MOST_VERTICES, BLOCK_EDGES, HELD = 4_000_000, 1_000_000, 500_000
#: Components of more edges than these are summed over packed edges, all others in kernels; up to so many packed edges a task holds for a sum.
LARGE, HELD_EDGES = 500_000, 24_000_000
RAW = "block int, s binary, t binary, p binary"


def _ints(x: bytes) -> np.ndarray:
    return np.frombuffer(x, np.int32)


def solve_blocks(blocks: list, weight: np.ndarray, prob: np.ndarray | None, c: float, tol: float) -> tuple[np.ndarray, int]:
    """(rank, rounds) of ``kernels.solve_series`` over blocks (heads, first, s, p); ``prob`` by source where it is even."""
    term, rank, rounds = weight.astype(float), weight.astype(float), 0
    while blocks and rounds < K.MAX_ROUNDS and term.max(initial=0) > tol:
        sent = c * term if prob is None else c * prob * term
        term = np.zeros(len(weight))
        for heads, first, s, p in blocks:
            x = sent[s]
            term[heads] += np.add.reduceat(x if p is None else x * p, first)
        rank += term
        rounds += 1
    if rounds >= K.MAX_ROUNDS and term.max(initial=0) > max(tol, 4e-16 * max(1.0, rank.max(initial=0))):
        raise K.Unfinished(f"not at {tol} after {rounds} rounds")
    return rank, rounds


class Packed:
    """A graph without loops as arrays over its sorted ids and packed edges."""

    def __init__(self, g: Graph):
        if g.vertices.limit(MOST_VERTICES + 1).count() > MOST_VERTICES:
            raise ValueError(f"packed passes take up to {MOST_VERTICES} vertices")
        got = g.vertices.select("id", "weight").toArrow()
        ids, order = got["id"].to_numpy(), np.argsort(got["id"].to_numpy())
        self.ids, self.weight, self.n = ids[order], got["weight"].to_numpy()[order].astype(float), len(ids)
        spark = self.spark = g.edges.sparkSession
        shares = g.edges.groupBy("src").agg(F.min("prob").alias("lo"), F.max("prob").alias("hi"), F.count("*").alias("n")).toArrow()
        self.edges = int(shares["n"].to_numpy().sum())
        self.even = bool((shares["lo"].to_numpy() == shares["hi"].to_numpy()).all())
        self.prob = np.zeros(self.n)  # of the edges of a source, where they are equal
        self.degree = np.zeros(self.n, np.int64)
        at = np.searchsorted(self.ids, shares["src"].to_numpy())
        self.prob[at], self.degree[at] = shares["lo"].to_numpy(), shares["n"].to_numpy()
        blocks = max(1, -(-self.edges // BLOCK_EDGES))
        width, even, n = -(-max(self.n, 1) // blocks), self.even, self.n
        shared = spark.sparkContext.broadcast(self.ids)

        def number(batches):
            ids, parts, held = shared.value, [], 0

            def flush():
                s, t = (np.searchsorted(ids, np.concatenate(x)).astype(np.int32) for x in ([q[0] for q in parts], [q[1] for q in parts]))
                p = np.concatenate([q[2] for q in parts])
                if (s == t).any():
                    raise ValueError("packed passes take no loops")
                by = np.argsort(t // width, kind="stable")
                cuts = np.searchsorted((t // width)[by], np.arange(blocks + 1))
                for k in np.flatnonzero(np.diff(cuts)):
                    at = by[cuts[k] : cuts[k + 1]]
                    yield pa.RecordBatch.from_pydict({"block": pa.array([k], pa.int32()), "s": [s[at].tobytes()], "t": [t[at].tobytes()], "p": pa.array([None if even else p[at].tobytes()], pa.binary())})

            for b in batches:
                parts.append(tuple(b.column(k).to_numpy(zero_copy_only=False) for k in range(3)))
                held += b.num_rows
                if held >= HELD:
                    yield from flush()
                    parts, held = [], 0
            if held:
                yield from flush()

        def pack(batches):
            got: dict[int, list] = {}
            for b in batches:
                for r in b.to_pylist():
                    got.setdefault(r["block"], []).append(r)
            for k in sorted(got):
                rows = got.pop(k)
                s, t = (np.concatenate([_ints(r[x]) for r in rows]) for x in "st")
                by = np.lexsort((s, t))
                heads, first = np.unique(t[by], return_index=True)
                p = None if even else np.concatenate([np.frombuffer(r["p"]) for r in rows])[by].tobytes()
                yield pa.RecordBatch.from_pydict({"heads": [heads.tobytes()], "first": [first.astype(np.int32).tobytes()], "s": [s[by].tobytes()], "p": pa.array([p], pa.binary())})

        dealt = g.edges.select("src", "dst", "prob").mapInArrow(number, RAW).repartition(blocks, "block")
        self.blocks = materialise(dealt.mapInArrow(pack, "heads binary, first binary, s binary, p binary"), "packed")
        shared.destroy()

    # ---------------------------------------------------------------- passes
    def over(self, make, schema: str, **arrays):
        """``make(heads, first, s, p, arrays) -> columns or None`` on every block: a frame; the arrays are sent to all tasks."""
        shared = self.spark.sparkContext.broadcast(arrays)

        def run(batches):
            for b in batches:
                for r in b.to_pylist():
                    out = make(_ints(r["heads"]), _ints(r["first"]), _ints(r["s"]), None if r["p"] is None else np.frombuffer(r["p"]), shared.value)
                    if out is not None:
                        yield pa.RecordBatch.from_pydict(out)

        return self.blocks.mapInArrow(run, schema), shared

    def results(self, make, **arrays) -> list[list[np.ndarray]]:
        """Arrays that ``make`` gives per block."""

        def raw(*a):
            got = make(*a)
            return {"x": pa.array([[x.tobytes() for x in got]], pa.list_(pa.binary())), "kind": pa.array([[x.dtype.str for x in got]], pa.list_(pa.string()))}

        frame, shared = self.over(raw, "x array<binary>, kind array<string>", **arrays)
        rows = frame.toArrow().to_pylist()
        shared.destroy()
        return [[np.frombuffer(x, np.dtype(kind)) for x, kind in zip(r["x"], r["kind"])] for r in rows]

    def sums(self, *vectors: tuple[np.ndarray, bool], comp: np.ndarray, c: float) -> list[np.ndarray]:
        """What comes to each vertex when all send their value of a vector, times c and the probability, along their edges,
        those inside components alone where asked."""
        even = self.even
        sent = {f"y{k}": c * self.prob * y if even else c * y for k, (y, _) in enumerate(vectors)}
        own = [inside for _, inside in vectors]

        def make(heads, first, s, p, a):
            out = [heads]
            same = a["comp"][s] == np.repeat(a["comp"][heads], np.diff(np.r_[first, len(s)])) if any(own) else None
            for k, inside in enumerate(own):
                x = a[f"y{k}"][s]
                x = x if p is None else x * p
                out.append(np.add.reduceat(np.where(same, x, 0.0) if inside else x, first))
            return out

        got = [np.zeros(self.n) for _ in vectors]
        for heads, *values in self.results(make, comp=comp.astype(np.int32) if any(own) else None, **sent):
            for y, x in zip(got, values):
                y[heads] += x
        return got

    def gathered(self, chosen: np.ndarray, make, schema: str, **arrays) -> pd.DataFrame:
        """``make(vertices, s, t, p, arrays)`` in one task over the chosen vertices and the edges between them (places among them)."""
        verts = np.flatnonzero(chosen)
        place = np.full(self.n, -1, np.int32)
        place[verts] = np.arange(len(verts))

        def pick(heads, first, s, p, a):
            t = a["place"][np.repeat(heads, np.diff(np.r_[first, len(s)]))]
            u = a["place"][s]
            on = (t >= 0) & (u >= 0)
            return {"k": pa.array([0], pa.int32()), "s": [u[on].tobytes()], "t": [t[on].tobytes()], "p": [(a["prob"][s[on]] if p is None else p[on]).tobytes()]}

        frame, shared = self.over(pick, "k int, s binary, t binary, p binary", place=place, prob=self.prob)
        extra = self.spark.sparkContext.broadcast(arrays)

        def solve(table: pd.DataFrame) -> pd.DataFrame:
            s, t = (np.concatenate([_ints(x) for x in table[k]]).astype(np.int64) for k in "st")
            return make(verts, s, t, np.concatenate([np.frombuffer(x) for x in table["p"]]), extra.value)

        out = frame.groupBy("k").applyInPandas(solve, schema).toArrow().to_pandas()
        shared.destroy()
        extra.destroy()
        return out

    def summed(self, group: np.ndarray, w: np.ndarray, c: float, tol: float) -> tuple[np.ndarray, np.ndarray]:
        """(rank, rounds of each vertex's set) of the series over sets of vertices, ``group`` their numbers from 0 or -1: each set goes
        all its rounds in one task that holds its packed edges."""
        n, even = self.n, self.even
        place = np.full(n, -1, np.int32)
        by = np.argsort(group, kind="stable")
        cuts = np.searchsorted(group[by], np.arange(group.max(initial=-1) + 2))
        for a, b in zip(cuts, cuts[1:]):
            place[by[a:b]] = np.arange(b - a)

        def pick(heads, first, s, p, a):
            at, out = a["group"][heads], {"k": [], "heads": [], "first": [], "s": [], "p": []}
            of = np.repeat(at, np.diff(np.r_[first, len(s)]))
            on = (of >= 0) & (a["group"][s] == of)
            for k in np.unique(of[on]):
                mine = np.flatnonzero(on & (of == k))
                to = a["place"][np.repeat(heads, np.diff(np.r_[first, len(s)]))[mine]]
                start = np.flatnonzero(np.r_[True, to[1:] != to[:-1]])
                for name, x in zip(out, (int(k), to[start].tobytes(), start.astype(np.int32).tobytes(), a["place"][s[mine]].tobytes(), None if p is None else p[mine].tobytes())):
                    out[name].append(x)
            return {name: pa.array(x, kind) for (name, x), kind in zip(out.items(), (pa.int32(), *[pa.binary()] * 4))} if out["k"] else None

        frame, shared = self.over(pick, "k int, heads binary, first binary, s binary, p binary", group=group.astype(np.int32), place=place)
        extra = self.spark.sparkContext.broadcast((by, cuts, w, self.prob))

        def go(table: pa.Table) -> pa.Table:
            by, cuts, w, prob = extra.value
            k = table["k"][0].as_py()
            verts = by[cuts[k] : cuts[k + 1]]
            blocks = [(*(_ints(r[x].as_buffer()) for x in ("heads", "first", "s")), None if even else np.frombuffer(r["p"].as_buffer())) for b in table.to_batches() for r in (dict(zip(b.schema.names, x)) for x in zip(*b.columns))]
            rank, rounds = solve_blocks(blocks, w[verts], prob[verts] if even else None, c, tol)
            return pa.table({"k": pa.array([k], pa.int32()), "rounds": pa.array([rounds], pa.int64()), "rank": pa.array([rank.tobytes()], pa.binary())})

        rows = frame.groupBy("k").applyInArrow(go, "k int, rounds long, rank binary").toArrow().to_pylist()
        shared.destroy()
        extra.destroy()
        rank, rounds = np.where(group >= 0, w, 0.0), np.zeros(n, np.int64)  # sets without edges keep their weights
        for r in rows:
            verts = by[cuts[r["k"]] : cuts[r["k"] + 1]]
            rank[verts], rounds[verts] = np.frombuffer(r["rank"]), r["rounds"]
        return rank, rounds

    # ---------------------------------------------------------------- components
    def strong(self, local_edges: int = LOCAL_EDGES) -> np.ndarray:
        """Smallest member of each vertex's strongly connected set: trimming, smallest colours forward, then backward inside a
        colour; what is left and fits goes to the kernel."""
        n, own = self.n, np.arange(self.n)
        out, active = own.copy(), np.ones(n, bool)

        def ends(heads, first, s, p, a):
            t = np.repeat(heads, np.diff(np.r_[first, len(s)]))
            on = a["active"][s] & a["active"][t]
            come, go = np.zeros(n, bool), np.zeros(n, bool)
            come[t[on]] = go[s[on]] = True
            return [np.packbits(come), np.packbits(go), np.array([np.count_nonzero(on)])]

        def colours(heads, first, s, p, a):
            offer = np.minimum.reduceat(np.where(a["active"][s], a["colour"][s], n), first)
            better = (offer < a["colour"][heads]) & a["active"][heads]
            return [heads[better], offer[better]]

        def back(heads, first, s, p, a):
            t = np.repeat(heads, np.diff(np.r_[first, len(s)]))
            on = a["found"][t] & a["active"][s] & ~a["found"][s] & (a["colour"][s] == a["colour"][t])
            go = np.zeros(n, bool)
            go[s[on]] = True
            return [np.packbits(go)]

        while active.any():
            while True:
                got = self.results(ends, active=active)
                come, go = (np.bitwise_or.reduce([np.unpackbits(r[k], count=n) for r in got]).astype(bool) if got else np.zeros(n, bool) for k in (0, 1))
                kept, m = active & come & go, sum(int(r[2][0]) for r in got)
                if m <= local_edges or (kept == active).all():
                    break
                active = kept
            if m <= local_edges:
                if m:
                    found = self.gathered(active, lambda v, s, t, p, a: pd.DataFrame({"v": v, "scc": v[K.local_scc(*K.rows(len(v), s, t)[:2])]}), "v long, scc long")
                    out[found["v"]] = found["scc"]
                return out
            colour = np.where(active, own, n).astype(np.int64)
            while True:
                moved = False
                for at, offer in self.results(colours, colour=colour, active=active):
                    colour[at], moved = np.minimum(colour[at], offer), moved or len(at) > 0
                colour[active] = colour[colour[active]]  # what reaches my colour reaches me
                if not moved:
                    break
            found = active & (colour == own)
            while True:
                got = self.results(back, colour=colour, active=active, found=found)
                new = np.bitwise_or.reduce([np.unpackbits(r[0], count=n) for r in got]).astype(bool) & ~found
                if not new.any():
                    break
                found |= new
            out[found] = colour[found]
            active &= ~found
        return out

    def levels(self, scc: np.ndarray, multi: np.ndarray) -> np.ndarray:
        """Longest way down, edges between single vertices at no cost."""
        n, level = self.n, np.zeros(self.n, np.int64)

        def offers(heads, first, s, p, a):
            t = np.repeat(heads, np.diff(np.r_[first, len(s)]))
            offer = a["level"][t] + (a["multi"][s] | a["multi"][t])
            on = (a["scc"][s] != a["scc"][t]) & (offer > a["level"][s])
            best = np.zeros(n, np.int64)
            np.maximum.at(best, s[on], offer[on])
            at = np.unique(s[on])
            return [at, best[at]]

        while True:
            moved = False
            for at, offer in self.results(offers, level=level, scc=scc, multi=multi):
                np.maximum.at(level, scc[at], offer)
                moved = moved or len(at) > 0
            level = level[scc]
            if not moved:
                return level

    def acyclic(self, level: np.ndarray, multi: np.ndarray) -> np.ndarray:
        """Smallest member of each single vertex's acyclic component."""
        n, label = self.n, np.arange(self.n)

        def offers(heads, first, s, p, a):
            t = np.repeat(heads, np.diff(np.r_[first, len(s)]))
            on = ~a["multi"][s] & ~a["multi"][t] & (a["level"][s] == a["level"][t])
            s, t = s[on], t[on]
            x, y = a["label"][s], a["label"][t]
            on = x != y
            return [np.maximum(x, y)[on], np.minimum(x, y)[on]]

        while True:
            moved = False
            for high, low in self.results(offers, label=label, level=level, multi=multi):
                np.minimum.at(label, high, low)
                moved = moved or len(high) > 0
            while (label[label] != label).any():
                label = label[label]
            if not moved:
                return label


class Run:
    """Ranks, components and rounds of a packed graph, level by level from the top, by series in every set on cycles; with ``whole``
    the rounds of the whole-graph series too."""

    def __init__(self, g: Packed, c: float, tol: float, local_edges: int = LOCAL_EDGES, large: int = LARGE, held: int = HELD_EDGES, whole: bool = True):
        n = g.n
        scc = g.strong(local_edges)
        multi = np.bincount(scc, minlength=n)[scc] > 1
        level = g.levels(scc, multi)
        comp = np.where(multi, scc, g.acyclic(level, multi))
        inside = np.zeros(n, np.int64)
        self.level, self.multi, self.inside = level, multi, inside

        def counted(heads, first, s, p, a):
            t = np.repeat(heads, np.diff(np.r_[first, len(s)]))
            at, k = np.unique(a["comp"][s][a["comp"][s] == a["comp"][t]], return_counts=True)
            return [at, k]

        for at, k in g.results(counted, comp=comp):
            inside[at] += k
        series = {"term": g.weight, "rounds": 0}
        if not whole:
            series["term"] = np.zeros(n)
        elif g.edges <= held:
            rounds = g.summed(np.zeros(n, np.int64), g.weight, c, tol)[1]
            series = {"term": np.zeros(n), "rounds": int(rounds.max(initial=0))}

        def sums(y: np.ndarray, own: bool) -> np.ndarray:
            """A pass for the levels; the series over the whole graph goes on in the same pass."""
            if series["term"].max(initial=0) <= tol:
                return g.sums((y, own), comp=comp, c=c)[0]
            got, series["term"] = g.sums((y, own), (series["term"], False), comp=comp, c=c)
            series["rounds"] += 1
            return got

        rank, w, rounds, solved = np.zeros(n), g.weight.copy(), np.zeros(n, np.int64), np.zeros(n, bool)
        from_level = np.bincount(level, g.degree)
        has_large = np.bincount(level[inside > large], minlength=level.max() + 1) > 0

        def in_kernels(chosen: np.ndarray) -> None:
            def solve(v, s, t, p, a):
                run = K.levelwise_local(len(v), s, t, p, a["w"], c, tol, policy=K.Policy(dense_below=0))
                took = np.zeros(len(v), np.int64)
                took[list(run.rounds)] = list(run.rounds.values())
                return pd.DataFrame({"v": v, "rank": run.rank, "rounds": took})

            got = g.gathered(chosen, solve, "v long, rank double, rounds long", w=w[chosen])
            rank[got["v"]], rounds[got["v"]] = got["rank"], got["rounds"]

        def in_tasks(chosen: np.ndarray) -> None:
            """Sets on cycles, each in a task of its own."""
            verts = np.flatnonzero(chosen)
            names, of = np.unique(comp[verts], return_inverse=True)
            group = np.full(n, -1, np.int64)
            group[verts] = of
            got, took = g.summed(group, w, c, tol)
            rank[verts] = got[verts]
            rounds[names] = took[names]

        def in_passes(chosen: np.ndarray) -> None:
            verts = np.flatnonzero(chosen)
            verts = verts[np.argsort(comp[verts], kind="stable")]
            names, first = np.unique(comp[verts], return_index=True)
            sizes = np.diff(np.r_[first, len(verts)])
            iterated = multi[names]
            term = np.where(chosen, w, 0.0)
            rank[chosen] = w[chosen]
            while True:
                top = np.maximum.reduceat(term[verts], first)
                on = np.where(iterated, top > tol, top > 0) & (sizes > 1)  # ways in an acyclic component end by themselves
                if not on.any():
                    return
                term[verts[~np.repeat(on, sizes)]] = 0
                term = sums(term, True)
                rank[chosen] += term[chosen]
                rounds[names[on & iterated]] += 1

        k = int(level.max(initial=-1))
        while k >= 0:
            low = k  # levels down to here go to one kernel
            while not has_large[k] and low > 0 and not has_large[low - 1] and from_level[low - 1 : k + 1].sum() <= local_edges:
                low -= 1
            here = (level >= low) & (level <= k)
            heavy = here & (inside[comp] > large)
            light = here & ~heavy
            if low < k:
                in_kernels(light)
            else:
                alone = light & (inside[comp] == 0)
                rank[alone] = w[alone]
                names = np.unique(comp[light & ~alone])
                turn = np.zeros(n, np.int64)  # about ``local_edges`` edges of whole components at a time
                turn[names] = (np.cumsum(inside[names]) - inside[names]) // max(local_edges, 1)
                for x in np.unique(turn[names]):
                    in_kernels(light & ~alone & (turn[comp] == x))
            tasks = heavy & multi & (inside[comp] <= held)
            if tasks.any():
                in_tasks(tasks)
            if (heavy & ~tasks).any():
                in_passes(heavy & ~tasks)
            solved |= here
            if low:
                gain = sums(np.where(here, rank, 0.0), False)
                w[~solved] += gain[~solved]
            k = low - 1
        while series["term"].max(initial=0) > tol:
            sums(np.zeros(n), False)
        self.rank, self.rounds, self.series_rounds = rank, rounds, series["rounds"]


def visits(g: Graph, c: float = 0.85, tol: float = 1e-9, threads: int = 4, local_edges: int = LOCAL_EDGES, large: int = LARGE, held: int = HELD_EDGES) -> dict[str, int]:
    """Edge visits, search included, of the whole-graph series, of the level-by-level method on both partitions and of its parallel
    form, by series in every set on cycles. Both partitions iterate the same sets from the same weights and use each other edge once, so their visits are equal."""
    g = Packed(g)
    m = g.edges
    if not m:
        return dict.fromkeys(("series", "levelwise_scc_cac", "levelwise_scc", "levelwise_parallel"), 0)
    run = Run(g, c, tol, local_edges, large, held)
    level, inside = run.level, run.inside
    cyclic = inside * run.multi
    cost = np.where(run.multi, inside * run.rounds, inside).astype(float)
    total, most = np.bincount(level, cost), np.zeros(level.max() + 1)
    np.maximum.at(most, level, cost)
    levelwise = int((cyclic * run.rounds).sum() + m - cyclic.sum() + 2 * m)
    parallel = int(2 * m + float(np.maximum(most, total / threads).sum()) + float(m - inside.sum()) / threads)
    return {"series": run.series_rounds * m, "levelwise_scc_cac": levelwise, "levelwise_scc": levelwise, "levelwise_parallel": parallel}


def packed_ranks(g: Graph, c: float = 0.85, tol: float = 1e-9, local_edges: int = LOCAL_EDGES, large: int = LARGE, held: int = HELD_EDGES) -> DataFrame:
    """(id, rank), level by level; loops are dropped."""
    packed = Packed(Graph(g.vertices, g.edges.where("src <> dst")))
    if not packed.n:
        return g.vertices.select("id", F.col("weight").alias("rank"))
    rank = Run(packed, c, tol, local_edges, large, held, whole=False).rank
    return materialise(g.edges.sparkSession.createDataFrame(pa.table({"id": packed.ids, "rank": rank})), "ranks")
