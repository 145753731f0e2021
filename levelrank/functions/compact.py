"""Kernels over a graph whose edges are kept as classes of targets that the same vertices lead to. No Spark here.

A class is a set of sources; a vertex belongs to one class and all its in-edges come from that class, but for itself where it is
one of the sources (``own``; graphs here have no loops). An edge's probability is its source's. Memory and a round's time follow the members of
the classes, not the edges, which are the same ones: every figure told is that of the edges. Sums add in another order than those over edges.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np

from levelrank.functions import kernels as K

#: Where taking a vertex's own share out of a sum leaves less than this part of it, the sum is added again without it.
LEFT = 1e-3


@dataclass
class Classes:
    """``prob`` and ``cls`` (-1: no in-edges) by vertex, ``own`` where it is a source of its class; ``es``, ``ek``: source and class of
    each member, sorted by class."""

    n: int
    k: int
    prob: np.ndarray
    cls: np.ndarray
    own: np.ndarray
    es: np.ndarray
    ek: np.ndarray

    def __post_init__(self):
        self.first = np.searchsorted(self.ek, np.arange(self.k + 1))
        self.mine = np.flatnonzero(self.own)
        sizes = np.r_[np.diff(self.first), 0]
        self.m = int(sizes[self.cls].sum()) - len(self.mine)

    def sums(self, y: np.ndarray, c: float) -> np.ndarray:
        """c times what comes to each vertex when all send ``y`` times their probability along their edges."""
        sent = c * self.prob * y
        total = np.r_[np.bincount(self.ek, sent[self.es], self.k), 0.0]
        out = total[self.cls]
        if len(self.mine):
            rest = out[self.mine] - sent[self.mine]
            for i in np.flatnonzero(np.abs(rest) < LEFT * np.abs(out[self.mine])):
                t = self.mine[i]
                s = self.es[self.first[self.cls[t]] : self.first[self.cls[t] + 1]]
                rest[i] = sent[s[s != t]].sum()
            out[self.mine] = rest
        return out

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        """(sources, targets), one by one: for small graphs."""
        t = np.flatnonzero(self.cls >= 0)
        sizes = np.diff(self.first)[self.cls[t]]
        at = np.repeat(self.first[self.cls[t]] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
        s, t = self.es[at], np.repeat(t, sizes)
        return s[s != t], t[s != t]

    def degree(self) -> np.ndarray:
        """Out-edges of each vertex."""
        size = np.bincount(self.cls[self.cls >= 0], minlength=self.k)
        return np.bincount(self.es, size[self.ek], self.n).astype(np.int64) - self.own

    def among(self, at: np.ndarray) -> Classes:
        """The graph of these vertices, in their order, where edges lead to none but them."""
        place = np.full(self.n, -1, np.int64)
        place[at] = np.arange(len(at))
        held = np.flatnonzero(place[self.es] >= 0)
        used, of = np.unique(self.ek[held], return_inverse=True)
        cls = self.cls[at]
        k = np.searchsorted(used, cls)
        k = np.where((cls >= 0) & (np.r_[used, -2][k] == cls), k, -1)
        return Classes(len(at), len(used), self.prob[at], k, self.own[at], place[self.es[held]], of)

    def to(self, at: np.ndarray) -> Classes:
        """The graph of the edges to these vertices."""
        cls, own = np.full(self.n, -1, np.int64), np.zeros(self.n, bool)
        used, cls_at = np.unique(self.cls[at], return_inverse=True)
        empty = int(len(used) > 0 and used[0] < 0)
        cls[at], own[at] = cls_at - empty, self.own[at]
        used = used[empty:]
        held = np.isin(self.ek, used)
        return Classes(self.n, len(used), self.prob, cls, own, self.es[held], np.searchsorted(used, self.ek[held]))

    def inside(self, comp: np.ndarray) -> tuple[Classes, np.ndarray]:
        """The graph of the edges inside components, its classes cut by component, and the number of those edges by component."""
        n, k = self.n, self.k
        on = np.flatnonzero(self.cls >= 0)
        keys, of, many = np.unique(comp[on].astype(np.int64) * k + self.cls[on], return_inverse=True, return_counts=True)
        cls = np.full(n, -1, np.int64)
        cls[on] = of
        wanted = comp[self.es].astype(np.int64) * k + self.ek
        at = np.minimum(np.searchsorted(keys, wanted), max(len(keys) - 1, 0))
        held = keys[at] == wanted if len(keys) else np.zeros(len(wanted), bool)
        es, ek = self.es[held], at[held]
        count = np.bincount(comp[es], many[ek], n).astype(np.int64)
        count -= np.bincount(comp[self.mine], minlength=n)
        by = np.argsort(ek, kind="stable")
        return Classes(n, len(keys), self.prob, cls, self.own, es[by], ek[by]), count


def partition(g: Classes) -> K.LocalPartition:
    """``kernels.local_partition`` of the same edges. Classes take part in the search as vertices between their sources and targets, and
    hand on the highest of their targets; vertices of their own in a set they are not."""
    n, k = g.n, g.k
    on = np.flatnonzero(g.cls >= 0)
    offsets, targets, _ = K.rows(n + k, np.r_[g.es, n + g.cls[on]], np.r_[n + g.ek, on])
    sets = K.closed_sets(offsets, targets)
    which = np.empty(n + k, np.int64)
    for i, group in enumerate(sets):
        which[group] = i
    real = np.bincount(which[:n], minlength=len(sets))
    multi = real[which[:n]] > 1
    low = np.full(len(sets), n + k, np.int64)
    np.minimum.at(low, which[:n], np.arange(n))
    scc = low[which[:n]]
    offs, tgts, of, many = offsets.tolist(), targets.tolist(), which.tolist(), multi.tolist()
    plain, level = [0] * n, [0] * n
    high, best, joined = [-1] * k, [-1] * k, [-1] * k  # of a class: largest depth, largest (level, cyclic), a vertex that stands for its highest
    forest = K.DisjointSet(n)

    def stands(a: int) -> int:
        """A highest target of the class, all of which are merged when first asked for."""
        if joined[a] < 0:
            tops = [t for t in tgts[offs[n + a] : offs[n + a + 1]] if level[t] == best[a] // 2]
            for t in tops[1:]:
                forest.merge(tops[0], t)
            joined[a] = tops[0]
        return joined[a]

    for i, group in enumerate(sets):
        members, depth, top, near = [x for x in group if x < n], 0, -1, []
        if members:
            for x in group:
                for y in tgts[offs[x] : offs[x + 1]]:
                    if of[y] == i:
                        continue
                    d, v = (plain[y], 2 * level[y] + many[y]) if y < n else (high[y - n], best[y - n])
                    depth = max(depth, d + 1)
                    if v > top:
                        top, near = v, [y]
                    elif v == top:
                        near.append(y)
            joins = len(members) == 1 and top >= 0 and top % 2 == 0
            for v in members:
                plain[v], level[v] = depth, top // 2 if joins else top // 2 + 1
            for y in near if joins else members[1:]:
                forest.merge(members[0], y if y < n else stands(y - n))
        for x in group:
            if x >= n:
                for t in tgts[offs[x] : offs[x + 1]]:
                    high[x - n], best[x - n] = max(high[x - n], plain[t]), max(best[x - n], 2 * level[t] + many[t])
    return K.LocalPartition(scc, multi, np.array(plain), np.array(level), forest.labels())


def series_stops(g: Classes, weight: np.ndarray, c: float, tolerances) -> list[tuple[np.ndarray, int, int, float]]:
    """``kernels.series_stops`` of the same edges."""
    term, rank, rounds, out, start = weight.astype(float), weight.astype(float), 0, {}, time.perf_counter()
    for tol in sorted(set(tolerances), reverse=True):
        while g.m and rounds < K.MAX_ROUNDS and term.max(initial=0) > tol:
            term = g.sums(term, c)
            rank += term
            rounds += 1
        K._checked(rounds, K.MAX_ROUNDS, term.max(initial=0), tol, rank.max(initial=0))
        out[tol] = rank.copy(), rounds, rounds * g.m, time.perf_counter() - start
    return [out[tol] for tol in tolerances]


def in_turns(g: Classes, weight: np.ndarray, c: float, tol: float, part: np.ndarray, most: int) -> tuple[np.ndarray, int]:
    """(ranks, sweeps) of x = W + Mx where the groups ``part`` take turns: a group's new changes are the scatter of the newest of all."""
    term, rank = np.zeros(g.n), np.zeros(g.n)
    groups = []
    for k in range(part.max(initial=-1) + 1):
        at = np.flatnonzero(part == k)
        groups.append((at, g.to(at)))
    for sweep in range(1, most + 1):
        for at, to in groups:
            term[at] = to.sums(term, c)[at] + (weight[at] if sweep == 1 else 0.0)
            rank[at] += term[at]
        if np.abs(term).max(initial=0) <= tol:
            return rank, sweep
    raise K.Unfinished(f"sweeps are not at {tol} after {most}")


@dataclass
class Run:
    rank: np.ndarray
    part: K.LocalPartition
    rounds: dict[int, int]
    visits: int
    longest: float


def levelwise(g: Classes, weight: np.ndarray, c: float, tol: float, kind: str = "scc_cac", part: K.LocalPartition | None = None, threads: int = 4) -> Run:
    """Level by level with every set on cycles by series: ``kernels.levelwise_local`` without dense solvers. The sets of a level go
    their rounds together, each to its own tolerance; ``longest`` are the visits on the longest way of ``threads`` threads, search included."""
    n, part = g.n, part or partition(g)
    level, comp = (part.level, part.component) if kind == "scc_cac" else (part.scc_level, part.scc)
    ins, count = g.inside(comp)
    rank, w, rounds = np.zeros(n), weight.astype(float), np.zeros(n, np.int64)
    for at in range(int(level.max(initial=-1)), -1, -1):
        here = np.flatnonzero(level == at)
        rank[here] = w[here]
        busy = here[count[comp[here]] > 0]
        if len(busy):
            busy = busy[np.argsort(comp[busy], kind="stable")]
            names, first = np.unique(comp[busy], return_index=True)
            sizes, cyclic = np.diff(np.r_[first, len(busy)]), part.multi[names]
            block = ins.among(busy)
            term, got = w[busy], w[busy].copy()
            while True:
                top = np.maximum.reduceat(term, first)
                go = np.where(cyclic, top > tol, top > 0)  # ways in an acyclic component end by themselves
                if not go.any():
                    break
                term = block.sums(np.where(np.repeat(go, sizes), term, 0.0), c)
                got += term
                rounds[names[go & cyclic]] += 1
                if rounds.max() >= K.MAX_ROUNDS:
                    K._checked(K.MAX_ROUNDS, K.MAX_ROUNDS, term.max(initial=0), tol, got.max(initial=0))
                    break
            rank[busy] = got
        if at:
            gain = g.sums(np.where(level == at, rank, 0.0), c)
            lower = level < at
            w[lower] += gain[lower]
    iterated = np.where(part.multi, count, 0)
    cost = np.where(part.multi, count * rounds, count).astype(float)
    total, most = np.bincount(level, cost, level.max(initial=0) + 1), np.zeros(level.max(initial=0) + 1)
    np.maximum.at(most, level, cost)
    between = g.m - int(count.sum())
    visits = int((iterated * rounds).sum()) + g.m - int(iterated.sum())
    longest = 2 * g.m + float(np.maximum(most, total / threads).sum()) + between / threads
    return Run(rank, part, {int(x): int(rounds[x]) for x in np.flatnonzero(rounds)}, visits, longest)


# ---------------------------------------------------------------- solvers over classes
def solve_series(g: Classes, weight: np.ndarray, c: float, tol: float, freeze: float = 0.0) -> tuple[np.ndarray, int, int]:
    """``kernels.solve_series`` of the same edges: (rank, rounds, edge visits)."""
    if not freeze:
        return series_stops(g, weight, c, (tol,))[0][:3]
    term, rank, rounds, visits, waiting, degree = weight.astype(float), weight.astype(float), 0, 0, np.zeros(g.n), g.degree()
    while g.m and rounds < K.MAX_ROUNDS and term.max(initial=0) + waiting.max(initial=0) > tol:
        waiting += term
        go = waiting > min(freeze, tol)
        if not go.any():
            break
        sent = np.where(go, waiting, 0.0)
        waiting[go] = 0
        term = g.sums(sent, c)
        visits += int(degree[go].sum())
        rank += term
        rounds += 1
    K._checked(rounds, K.MAX_ROUNDS, term.max(initial=0), tol, rank.max(initial=0))
    return rank, rounds, visits


def _until(step, x: np.ndarray, tol: float) -> tuple[np.ndarray, int]:
    """(x, rounds) of x = step(x) until no entry changes by more than ``tol`` or than doubles can."""
    rounds, change = 0, np.inf
    while rounds < K.MAX_ROUNDS and change > tol:
        new = step(x)
        change, x, rounds = np.abs(new - x).max(initial=0), new, rounds + 1
        if change <= 4e-16 * x.max(initial=0):
            break
    K._checked(rounds, K.MAX_ROUNDS, change, tol, x.max(initial=0))
    return x, rounds


def solve_jacobi(g: Classes, weight: np.ndarray, c: float, tol: float) -> tuple[np.ndarray, int]:
    return _until(lambda x: weight + g.sums(x, c), weight.astype(float), tol)


def solve_power(g: Classes, weight: np.ndarray, c: float, tol: float) -> tuple[np.ndarray, np.ndarray, int]:
    total = weight.sum()
    w = weight / total if total else weight.astype(float)

    def step(x):
        y = g.sums(x, c)
        return y + (1 - y.sum()) * w

    x, rounds = _until(step, w.copy(), tol)
    lost = 1 - g.sums(x, c).sum()
    return x, x * total / lost if lost else x, rounds


def solve_gauss_seidel(g: Classes, weight: np.ndarray, c: float, tol: float) -> tuple[np.ndarray, int]:
    """Vertex by vertex in their order with the newest values: what a class has gathered follows each change, and is added anew every sweep."""
    by = np.argsort(g.es, kind="stable")
    of, at = g.ek[by].tolist(), np.searchsorted(g.es[by], np.arange(g.n + 1)).tolist()
    cls, own, share, w = g.cls.tolist(), g.own.tolist(), (c * g.prob).tolist(), weight.astype(float).tolist()

    def step(x):
        got = np.bincount(g.ek, (c * g.prob * x)[g.es], g.k).tolist()
        old, new = x.tolist(), w.copy()
        for t in range(g.n):
            k = cls[t]
            if k >= 0:
                new[t] += got[k] - share[t] * old[t] if own[t] else got[k]
            d = share[t] * (new[t] - old[t])
            for i in range(at[t], at[t + 1]):
                got[of[i]] += d
        return np.array(new)

    return _until(step, weight.astype(float), tol)


def _small(g: Classes, c: float) -> tuple[np.ndarray, np.ndarray]:
    """(d, G): x = d * (weight + c * what the vertex's class gathers), and G times what classes gather = what they gather of d * weight."""
    d = 1 / (1 + c * g.prob * g.own)
    small, on = np.eye(g.k), g.cls[g.es] >= 0
    np.add.at(small, (g.ek[on], g.cls[g.es[on]]), -c * (g.prob * d)[g.es[on]])
    return d, small


def solve_dense(g: Classes, weight: np.ndarray, c: float) -> np.ndarray:
    """The linear system, direct, with one unknown a class."""
    d, small = _small(g, c)
    gathered = np.linalg.solve(small, np.bincount(g.ek, (g.prob * d * weight)[g.es], g.k))
    return d * (weight + c * np.r_[gathered, 0.0][g.cls])


def solve_hits(g: Classes, weight: np.ndarray, c: float) -> np.ndarray:
    """``kernels.solve_hits``: start weights times chances to hit, times one plus the expected returns. The visits of a vertex to itself
    are the inverse's diagonal, which follows from the inverse of the system of classes."""
    d, small = _small(g, c)
    inverse = np.linalg.inv(small)
    gathered = inverse @ np.bincount(g.ek, (g.prob * d * weight)[g.es], g.k)
    total = d * (weight + c * np.r_[gathered, 0.0][g.cls])
    on = g.cls[g.es] >= 0
    back = np.bincount(g.es[on], inverse[g.cls[g.es[on]], g.ek[on]], g.n)
    visits = d + c * d * d * g.prob * back
    hit = total / visits
    return hit * visits


def by_policy(g: Classes, weight: np.ndarray, c: float, tol: float, kind: str = "scc_cac", part: K.LocalPartition | None = None, policy: K.Policy | None = None, merge_below: int = 0) -> Run:
    """``kernels.levelwise_local`` of the same edges, component by component, each by its solver."""
    n, part, policy = g.n, part or partition(g), policy or K.Policy()
    level = (part.level if kind == "scc_cac" else part.scc_level).copy()
    comp, solid = (part.component if kind == "scc_cac" else part.scc).copy(), part.multi.copy()
    if merge_below:
        level, comp, solid = K.merged_levels(level, comp, solid, merge_below)
    ins, count = g.inside(comp)
    rank, w, rounds, visits = np.zeros(n), weight.astype(float), {}, g.m - int(count.sum())
    order = np.argsort(comp, kind="stable")
    members = dict(zip(*(x.tolist() if i == 0 else np.split(order, x[1:]) for i, x in enumerate(np.unique(comp[order], return_index=True))))) if n else {}
    for at in range(int(level.max(initial=-1)), -1, -1):
        here = np.flatnonzero(level == at)
        rank[here] = w[here]
        for label in np.unique(comp[here[count[comp[here]] > 0]]).tolist():
            m = members[label]
            block = ins.among(m)
            if not solid[m[0]] and policy.acyclic == "acyclic":
                term, rank[m] = w[m], w[m]
                while term.max(initial=0) > 0:
                    term = block.sums(term, c)
                    rank[m] += term
                visits += block.m
            elif len(m) < policy.dense_below and policy.small == "dense":
                s, t = block.edges()
                rank[m] = K.solve_dense(len(m), s, t, block.prob[s], w[m], c)
                visits += block.m
            elif policy.large == "gauss_seidel":
                rank[m], rounds[label] = solve_gauss_seidel(block, w[m], c, tol)
                visits += rounds[label] * block.m
            else:
                rank[m], rounds[label], seen = solve_series(block, w[m], c, tol, tol if policy.large == "adaptive" else 0.0)
                visits += seen
        if at:
            gain = g.sums(np.where(level == at, rank, 0.0), c)
            w[level < at] += gain[level < at]
    return Run(rank, part, rounds, visits, np.nan)
