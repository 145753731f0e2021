"""NumPy kernels over one block of a graph in compressed row form. No Spark here.

Vertices are 0..n-1 and edge (s, t) sits at ``targets[offsets[s]:offsets[s+1]]``. The
search keeps its own stack, so depth is bounded by memory only.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np

SCC, CAC = "scc", "cac"


def rows(n: int, src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(offsets, targets, order): edges sorted by source; ``order`` maps them to the input."""
    order = np.argsort(src, kind="stable")
    return np.concatenate([[0], np.cumsum(np.bincount(src, minlength=n))]).astype(np.int64), dst[order], order


class DisjointSet:
    """Merge-find forest with path shortening; with ``by_depth`` the shallower tree goes
    under the deeper one, without it one array less is kept."""

    def __init__(self, n: int, by_depth: bool = True):
        self.parent = list(range(n))
        self.depth = [0] * n if by_depth else None

    def find(self, x: int) -> int:
        p = self.parent
        while p[x] != x:
            p[x] = p[p[x]]
            x = p[x]
        return x

    def merge(self, a: int, b: int) -> None:
        a, b = self.find(a), self.find(b)
        if a == b:
            return
        if self.depth is not None:
            if self.depth[a] < self.depth[b]:
                a, b = b, a
            self.depth[a] += self.depth[a] == self.depth[b]
        self.parent[b] = a

    def labels(self) -> np.ndarray:
        """Smallest member of each vertex's set, by n finds."""
        roots = np.fromiter(map(self.find, range(len(self.parent))), np.int64, len(self.parent))
        low = np.full(len(roots), len(roots), np.int64)
        np.minimum.at(low, roots, np.arange(len(roots)))
        return low[roots]


def closed_sets(offsets: np.ndarray, targets: np.ndarray) -> list[list[int]]:
    """Strongly connected sets in the order the search closes them: each set after all it reaches."""
    n = len(offsets) - 1
    offs, tgts = offsets.tolist(), memoryview(np.ascontiguousarray(targets))  # edges stay as they are, numbers of Python would take five times the room
    seen, low, on = [0] * n, [0] * n, [False] * n
    clock, held, out = 0, [], []
    for root in range(n):
        if seen[root]:
            continue
        path = [(root, offs[root])]
        clock += 1
        seen[root] = low[root] = clock
        held.append(root)
        on[root] = True
        while path:
            v, i = path.pop()
            if i < offs[v + 1]:
                path.append((v, i + 1))
                w = tgts[i]
                if not seen[w]:
                    clock += 1
                    seen[w] = low[w] = clock
                    held.append(w)
                    on[w] = True
                    path.append((w, offs[w]))
                elif on[w] and seen[w] < low[v]:
                    low[v] = seen[w]
                continue
            if path and low[v] < low[path[-1][0]]:
                low[path[-1][0]] = low[v]
            if low[v] == seen[v]:
                group = []
                while True:
                    w = held.pop()
                    on[w] = False
                    group.append(w)
                    if w == v:
                        break
                out.append(group)
    return out


def local_scc(offsets: np.ndarray, targets: np.ndarray) -> np.ndarray:
    """Smallest member of each vertex's strongly connected set."""
    out = np.empty(len(offsets) - 1, np.int64)
    for group in closed_sets(offsets, targets):
        out[group] = min(group)
    return out


@dataclass
class LocalPartition:
    scc: np.ndarray
    multi: np.ndarray
    scc_level: np.ndarray
    level: np.ndarray
    component: np.ndarray


def local_partition(n: int, src: np.ndarray, dst: np.ndarray, by_depth: bool = True) -> LocalPartition:
    """Components and levels in one walk over the sets as they close.

    A set's neighbours are closed before it, so both levels are final at once: one above
    the highest neighbour, or on it where the set is one vertex and all of its highest
    neighbours are too; then it joins their acyclic component."""
    keep = src != dst
    offsets, targets, _ = rows(n, src[keep], dst[keep])
    sets = closed_sets(offsets, targets)
    scc, multi = np.empty(n, np.int64), np.zeros(n, bool)
    for group in sets:
        scc[group] = min(group)
        multi[group] = len(group) > 1
    plain, level = [0] * n, [0] * n
    forest = DisjointSet(n, by_depth)
    source = np.repeat(np.arange(n), np.diff(offsets))
    leaves = scc[source] != scc[targets]  # edges inside sets are not walked again
    offsets, targets, _ = rows(n, source[leaves], targets[leaves])
    offs, tgts, many = offsets.tolist(), targets.tolist(), multi.tolist()
    for group in sets:
        depth, top, mixed, near = 0, -1, False, []
        for v in group:
            for w in tgts[offs[v] : offs[v + 1]]:
                depth = max(depth, plain[w] + 1)
                if level[w] > top:
                    top, mixed, near = level[w], many[w], [w]
                elif level[w] == top:
                    mixed |= many[w]
                    near.append(w)
        joins = len(group) == 1 and top >= 0 and not mixed
        for v in group:
            plain[v], level[v] = depth, top if joins else top + 1
        for w in near if joins else group[1:]:
            forest.merge(group[0], w)
    return LocalPartition(scc, multi, np.array(plain), np.array(level), forest.labels())


# ---------------------------------------------------------------- solvers
class Unfinished(RuntimeError):
    """A loop reached its bound of rounds before its tolerance."""


MAX_ROUNDS = 1_000_000


def _checked(rounds: int, max_rounds: int, change: float, tol: float, scale: float) -> None:
    """Raise unless the loop ended by its tolerance, or where doubles of this size cannot move any more."""
    if rounds >= max_rounds and change > max(tol, 4e-16 * max(1.0, scale)):
        raise Unfinished(f"not at {tol} after {rounds} rounds")


def solve_acyclic(n: int, src: np.ndarray, dst: np.ndarray, prob: np.ndarray, weight: np.ndarray, c: float, loop: np.ndarray | None = None) -> np.ndarray:
    """Each edge once: a wave of vertices whose in-edges are all done hands its rank on."""
    rank = weight.astype(float)
    scale = 1 / (1 - c * loop) if loop is not None else np.ones(n)
    open_in = np.bincount(dst, minlength=n)
    offsets, targets, order = rows(n, src, dst)
    prob = prob[order]
    wave = np.flatnonzero(open_in == 0)
    while len(wave):
        rank[wave] *= scale[wave]
        sizes = offsets[wave + 1] - offsets[wave]
        at = np.repeat(offsets[wave] - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
        np.add.at(rank, targets[at], c * prob[at] * np.repeat(rank[wave], sizes))
        np.subtract.at(open_in, targets[at], 1)
        reached = np.unique(targets[at])
        wave = reached[open_in[reached] == 0]
    return rank


def dense_matrix(n: int, src: np.ndarray, dst: np.ndarray, prob: np.ndarray, c: float) -> np.ndarray:
    """I - c * (transposed probabilities)."""
    m = np.eye(n)
    np.add.at(m, (dst, src), -c * prob)
    return m


#: Vertices up to which LAPACK's solver and its copies are taken; over it the matrix is factored where it lies, in panels.
DENSE_VERTICES, PANEL = 5_000, 256


def factor(m: np.ndarray, panel: int = PANEL) -> np.ndarray:
    """L and U in the place of ``m``, whose columns are dominated by their diagonal, so no rows are exchanged."""
    n = len(m)
    for a in range(0, n, panel):
        b = min(a + panel, n)
        d = m[a:b, a:b]
        for k in range(b - a - 1):
            d[k + 1 :, k] /= d[k, k]
            d[k + 1 :, k + 1 :] -= np.outer(d[k + 1 :, k], d[k, k + 1 :])
        if b == n:
            break
        m[a:b, b:] = np.linalg.solve(np.tril(d, -1) + np.eye(b - a), m[a:b, b:])
        m[b:, a:b] = np.linalg.solve(np.triu(d).T, m[b:, a:b].T).T
        for r in range(b, n, 4 * panel):
            m[r : r + 4 * panel, b:] -= m[r : r + 4 * panel, a:b] @ m[a:b, b:]
    return m


def substitute(m: np.ndarray, right: np.ndarray, panel: int = PANEL) -> np.ndarray:
    """x of the factored system."""
    n, x = len(m), right.astype(float)
    for a in range(0, n, panel):
        b = min(a + panel, n)
        x[a:b] = np.linalg.solve(np.tril(m[a:b, a:b], -1) + np.eye(b - a), x[a:b] - m[a:b, :a] @ x[:a])
    for a in reversed(range(0, n, panel)):
        b = min(a + panel, n)
        x[a:b] = np.linalg.solve(np.triu(m[a:b, a:b]), x[a:b] - m[a:b, b:] @ x[b:])
    return x


def inverse_diagonal(m: np.ndarray, panel: int = PANEL) -> np.ndarray:
    """Diagonal of the inverse of the factored matrix; L and U are inverted where they lie, panel by panel from the end."""
    n = len(m)
    cuts = [(a, min(a + panel, n)) for a in range(0, n, panel)]
    out = np.zeros(n)
    for a, b in reversed(cuts):
        low, up = np.linalg.inv(np.tril(m[a:b, a:b], -1) + np.eye(b - a)), np.linalg.inv(np.triu(m[a:b, a:b]))
        for r, q in reversed([x for x in cuts if x[0] > a]):  # from below: a panel reads those over it, which are not replaced yet
            own = m[r:q, r:q]
            m[r:q, a:b] = -(m[r:q, b:r] @ m[b:r, a:b] + (np.tril(own, -1) + np.eye(q - r)) @ m[r:q, a:b]) @ low
        for r, q in reversed([x for x in cuts if x[0] > a]):
            own = m[r:q, r:q]
            m[a:b, r:q] = -up @ (m[a:b, b:r] @ m[b:r, r:q] + m[a:b, r:q] @ np.triu(own))
        out[a:b] = np.einsum("ij,ji->i", up, low)
        m[a:b, a:b] = np.tril(low, -1) + np.triu(up)
        out[a:b] += np.einsum("ij,ji->i", m[a:b, b:], m[b:, a:b])
    return out


def solve_dense(n, src, dst, prob, weight, c, most: int = DENSE_VERTICES) -> np.ndarray:
    m = dense_matrix(n, src, dst, prob, c)
    return np.linalg.solve(m, weight) if n <= most else substitute(factor(m), weight)


def solve_series(n, src, dst, prob, weight, c, tol, max_rounds=MAX_ROUNDS, freeze: float = 0.0) -> tuple[np.ndarray, int, int]:
    """Sum of the terms W, MW, MMW, ...: (rank, rounds, edge visits). Stops when no entry of
    the last term is over ``tol``. With ``freeze`` entries below it wait until they have gathered more."""
    term, rank, rounds, visits, waiting, share = weight.astype(float), weight.astype(float), 0, 0, np.zeros(n), c * prob
    while len(src) and rounds < max_rounds and (term.max(initial=0) + waiting.max(initial=0)) > tol:
        if freeze:
            waiting += term
            go = waiting > min(freeze, tol)
            if not go.any():
                break
            sent = np.where(go, waiting, 0.0)
            waiting[go] = 0
            live = go[src]
            term = np.bincount(dst[live], share[live] * sent[src[live]], n)
            visits += int(live.sum())
        else:
            term = np.bincount(dst, share * term[src], n)
            visits += len(src)
        rank += term
        rounds += 1
    _checked(rounds, max_rounds, term.max(initial=0), tol, rank.max(initial=0))
    return rank, rounds, visits


def series_stops(n, src, dst, prob, weight, c, tolerances, max_rounds=MAX_ROUNDS) -> list[tuple[np.ndarray, int, int, float]]:
    """(rank, rounds, edge visits, seconds) of ``solve_series`` at each tolerance, from one run: a tighter one only goes on."""
    term, rank, rounds, share, out, start = weight.astype(float), weight.astype(float), 0, c * prob, {}, time.perf_counter()
    for tol in sorted(set(tolerances), reverse=True):
        while len(src) and rounds < max_rounds and term.max(initial=0) > tol:
            term = np.bincount(dst, share * term[src], n)
            rank += term
            rounds += 1
        _checked(rounds, max_rounds, term.max(initial=0), tol, rank.max(initial=0))
        out[tol] = rank.copy(), rounds, rounds * len(src), time.perf_counter() - start
    return [out[tol] for tol in tolerances]


def solve_jacobi(n, src, dst, prob, weight, c, tol, max_rounds=MAX_ROUNDS) -> tuple[np.ndarray, int]:
    """x = W + Mx from x = W; the same iterates as the series."""
    x, rounds, change = weight.astype(float), 0, np.inf
    while rounds < max_rounds and change > tol:
        new = weight + np.bincount(dst, c * prob * x[src], n) if len(src) else weight.astype(float)
        change, x, rounds = np.abs(new - x).max(initial=0), new, rounds + 1
        if change <= 4e-16 * x.max(initial=0):
            break
    _checked(rounds, max_rounds, change, tol, x.max(initial=0))
    return x, rounds


def solve_gauss_seidel(n, src, dst, prob, weight, c, tol, max_rounds=MAX_ROUNDS) -> tuple[np.ndarray, int]:
    """Sweeps that use the newest values, one vertex after the other in their order. What vertices take from those after
    them, old values, is one scatter; those before them are met in waves: a wave waits only for the waves before it."""
    own = src == dst
    held = 1 - np.bincount(src[own], c * prob[own], n)
    new_in = src < dst
    s, t, p = src[new_in], dst[new_in], c * prob[new_in]
    depth = depths(n, s, t)
    order, by = np.argsort(depth[t], kind="stable"), np.argsort(depth, kind="stable")
    place = np.empty(n, np.int64)
    cuts, e_cuts = (np.searchsorted(depth[x], np.arange(depth.max(initial=-1) + 2)).tolist() for x in (by, t[order]))
    for a, b in zip(cuts, cuts[1:]):
        place[by[a:b]] = np.arange(b - a)
    s, at, p = s[order], place[t[order]], p[order]
    after = src > dst
    os, ot, op = src[after], dst[after], c * prob[after]
    x, rounds, change = weight.astype(float), 0, np.inf
    while rounds < max_rounds and change > tol:
        new = weight + np.bincount(ot, op * x[os], n)
        for (a, b), (i, j) in zip(zip(cuts, cuts[1:]), zip(e_cuts, e_cuts[1:])):
            wave = by[a:b]
            new[wave] = (new[wave] + np.bincount(at[i:j], p[i:j] * new[s[i:j]], b - a)) / held[wave]
        change, x, rounds = np.abs(new - x).max(initial=0), new, rounds + 1
        if change <= 4e-16 * x.max(initial=0):
            break
    _checked(rounds, max_rounds, change, tol, x.max(initial=0))
    return x, rounds


def depths(n: int, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Edges on the longest way to each vertex of a graph without cycles."""
    depth, open_in = np.zeros(n, np.int64), np.bincount(dst, minlength=n)
    offsets, targets, _ = rows(n, src, dst)
    wave, k = np.flatnonzero(open_in == 0), 0
    while len(wave):
        depth[wave], k = k, k + 1
        sizes = offsets[wave + 1] - offsets[wave]
        to = targets[np.repeat(offsets[wave] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())]
        reached, came = np.unique(to, return_counts=True)
        open_in[reached] -= came
        wave = reached[open_in[reached] == 0]
    return depth


def solve_power(n, src, dst, prob, weight, c, tol, max_rounds=MAX_ROUNDS) -> tuple[np.ndarray, np.ndarray, int]:
    """Power iteration on the normalised form; all mass that leaves the block comes back by
    the start distribution. Returns (normalised, rescaled to the start weights, rounds)."""
    total = weight.sum()
    w = weight / total if total else weight.astype(float)
    x, rounds, change = w.copy(), 0, np.inf
    moved = lambda y: np.bincount(dst, c * prob * y[src], n) if len(src) else np.zeros(n)
    while rounds < max_rounds and change > tol:
        y = moved(x)
        new = y + (1 - y.sum()) * w
        change, x, rounds = np.abs(new - x).max(initial=0), new, rounds + 1
        if change <= 4e-16 * x.max(initial=0):
            break
    _checked(rounds, max_rounds, change, tol, x.max(initial=0))
    lost = 1 - moved(x).sum()
    return x, x * total / lost if lost else x, rounds


def solve_hits(n, src, dst, prob, weight, c, most: int = DENSE_VERTICES) -> np.ndarray:
    """Expected visits by the random walk: start weights times chances to hit, times one
    plus the expected returns. Over ``most`` vertices the inverse is never whole: chances to hit are the solution over the
    visits of a vertex to itself."""
    if n > most:
        m = factor(dense_matrix(n, src, dst, prob, c))
        total = substitute(m, weight)
        visits = inverse_diagonal(m)
        return (total / visits) * visits
    full = np.linalg.inv(dense_matrix(n, src, dst, prob, c))  # full[v, u]: visits of v from u
    visits = np.diag(full)
    hit = full / visits[:, None]
    return (hit @ weight) * visits


@dataclass
class Policy:
    """Which solver takes which component."""

    dense_below: int = 100
    large: str = "series"
    acyclic: str = "acyclic"
    small: str = "dense"
    log: dict = field(default_factory=dict)


def solve_components(n, src, dst, prob, weight, c, tol, component: np.ndarray, solver: np.ndarray, policy: Policy) -> np.ndarray:
    """Ranks of components without edges between them, each by its named solver; edges may hold loops."""
    rank, local = np.zeros(n), np.empty(n, np.int64)
    by, e_by = np.argsort(component, kind="stable"), np.argsort(component[src], kind="stable")
    edge = np.searchsorted(component[src][e_by], np.arange(component.max(initial=-1) + 2))
    part = np.searchsorted(component[by], np.arange(component.max(initial=-1) + 2))
    for k in range(len(part) - 1):
        m, e = by[part[k] : part[k + 1]], e_by[edge[k] : edge[k + 1]]
        local[m] = np.arange(len(m))
        s, t, p = local[src[e]], local[dst[e]], prob[e]
        kind, own = solver[m[0]], s == t
        if kind == "acyclic" and policy.acyclic == "acyclic":
            loop = np.bincount(s[own], p[own], len(m))
            rank[m] = solve_acyclic(len(m), s[~own], t[~own], p[~own], weight[m], c, loop)
        elif kind == "dense" and policy.small == "dense":
            rank[m] = solve_dense(len(m), s, t, p, weight[m], c)
        elif policy.large == "gauss_seidel":
            rank[m] = solve_gauss_seidel(len(m), s, t, p, weight[m], c, tol)[0]
        else:
            rank[m] = solve_series(len(m), s, t, p, weight[m], c, tol, freeze=tol if policy.large == "adaptive" else 0.0)[0]
    return rank


def merged_levels(level: np.ndarray, comp: np.ndarray, solid: np.ndarray, below: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Adjacent levels of under ``below`` vertices become one block each, solved as if strongly connected."""
    comp, solid = comp.copy(), solid.copy()
    sizes, group = np.bincount(level), np.zeros(level.max() + 1, int)
    for k in range(1, len(sizes)):
        group[k] = group[k - 1] + (sizes[k] >= below or sizes[k - 1] >= below)
    fused = np.bincount(group) > 1
    level = group[level]
    for k in np.flatnonzero(fused):
        at = level == k
        comp[at], solid[at] = np.flatnonzero(at)[0], True
    return level, comp, solid


@dataclass
class LocalRun:
    rank: np.ndarray
    part: LocalPartition
    rounds: dict[int, int]
    visits: int
    iterated: int


def levelwise_local(n, src, dst, prob, weight, c=0.85, tol=1e-9, kind="scc_cac", loops="drop", policy: Policy | None = None, merge_below: int = 0, handover: str = "level", stop_level: int = 0, workers: int = 1, part: LocalPartition | None = None) -> LocalRun:
    """Level-by-level ranks of one block, the components of a level one after the other or by ``workers`` threads. ``kind`` 'scc' uses plain levels; ``handover`` is 'level' (one scatter
    per level), 'component' (a scatter per component) or 'pull' (a level gathers all it gets from above)."""
    policy = policy or Policy()
    own = src == dst
    loop = np.bincount(src[own], prob[own], n) if loops == "keep" else np.zeros(n)
    src, dst, prob = src[~own], dst[~own], prob[~own]
    part = part or local_partition(n, src, dst)
    level = (part.level if kind == "scc_cac" else part.scc_level).copy()
    comp = (part.component if kind == "scc_cac" else part.scc).copy()
    solid = part.multi.copy()
    if merge_below:
        level, comp, solid = merged_levels(level, comp, solid, merge_below)
    inside = comp[src] == comp[dst]
    rank, w, rounds, visits = np.zeros(n), weight.astype(float), {}, 0
    by_comp = np.argsort(comp, kind="stable")
    starts = np.flatnonzero(np.r_[True, np.diff(comp[by_comp]) != 0])
    members = {int(comp[by_comp[a]]): by_comp[a:b] for a, b in zip(starts, np.r_[starts[1:], n])} if n else {}
    e_in = np.flatnonzero(inside)
    e_in = e_in[np.argsort(comp[src[e_in]], kind="stable")]
    e_comp = comp[src[e_in]]
    local = np.empty(n, np.int64)
    out_edges = np.flatnonzero(~inside)
    at_level = level[src[out_edges]] if len(out_edges) else out_edges
    into = level[dst[out_edges]] if len(out_edges) else out_edges

    if handover == "component":  # between-edges by their source's component
        out_edges = out_edges[np.argsort(comp[src[out_edges]], kind="stable")]
    out_comp, sizes_of = comp[src[out_edges]], np.bincount(comp, minlength=n)

    def solve(label: int) -> tuple[np.ndarray, int | None, int]:
        """(ranks, rounds if iterated, edge visits) of one component."""
        m = members[label]
        e = e_in[np.searchsorted(e_comp, label) : np.searchsorted(e_comp, label, "right")]
        local[m] = np.arange(len(m))
        s, t, p = local[src[e]], local[dst[e]], prob[e]
        if loops == "keep" and solid[m[0]]:
            held = np.flatnonzero(loop[m] > 0)
            s, t, p = np.r_[s, held], np.r_[t, held], np.r_[p, loop[m][held]]
        if not solid[m[0]] and policy.acyclic == "acyclic":
            return solve_acyclic(len(m), s, t, p, w[m], c, loop[m]), None, len(e)
        if len(m) < policy.dense_below and policy.small == "dense":
            return solve_dense(len(m), s, t, p, w[m], c), None, len(e)
        if policy.large == "gauss_seidel":
            got, done = solve_gauss_seidel(len(m), s, t, p, w[m], c, tol)
            return got, done, len(e) * done
        return solve_series(len(m), s, t, p, w[m], c, tol, freeze=tol if policy.large == "adaptive" else 0.0)

    pool = ThreadPoolExecutor(workers) if workers > 1 else None
    map_ = pool.map if pool else map

    def scatter(e: np.ndarray) -> None:
        nonlocal visits
        np.add.at(w, dst[e], c * prob[e] * rank[src[e]])
        visits += len(e)

    for k in range(int(level.max(initial=0)), stop_level - 1, -1):
        if handover == "pull":
            scatter(out_edges[into == k])
        here = np.flatnonzero(level == k)
        labels = np.unique(comp[here]).tolist()
        alone = here[sizes_of[comp[here]] == 1]
        rank[alone] = w[alone] / (1 - c * loop[alone])  # single vertices are pooled
        many = [x for x in labels if len(members[x]) > 1]
        for label, (got, done, seen) in zip(many, map_(solve, many)):
            rank[members[label]] = got
            visits += seen
            if done is not None:
                rounds[label] = done
        if handover == "component":
            for label in labels:
                scatter(out_edges[np.searchsorted(out_comp, label) : np.searchsorted(out_comp, label, "right")])
        if handover == "level":
            scatter(out_edges[at_level == k])
    if pool:
        pool.shutdown()
    pending = level < stop_level
    rank[pending] = w[pending]  # weights handed down so far
    iterated = int((inside & solid[src]).sum()) if len(src) else 0
    return LocalRun(rank, part, rounds, visits, iterated)
