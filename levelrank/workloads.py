"""The experiments as functions: sweeps over tolerance and damping, methods side by side, ten copies, steps.

Costs are edge visits, which do not depend on the machine, with the seconds of the kernels beside them. A
sweep runs in one task, whatever the size of the graph: its memory follows the edges, or where the graph is large and many vertices
have the same sources (``operators/twins.py``) the members of their classes. ``seconds_by_step`` runs on frames,
``copies_scale`` in passes over packed edges where the graph is large and classes do not win.
"""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.functions import compact as C
from levelrank.functions import kernels as K
from levelrank.functions import measures as M
from levelrank.operators import rank as R
from levelrank.operators.model import LOCAL_EDGES, Graph, Partition
from levelrank.operators.packed import MOST_VERTICES
from levelrank.operators.packed import visits as packed_visits
from levelrank.operators.partition import in_one_task, numbered, partition
from levelrank.operators.twins import classes, in_task
from levelrank.plans.blocks import classify_edges, plan_blocks
from levelrank.plans.staging import materialise

TOLERANCES = tuple(10.0**-k for k in range(1, 16, 2))
#: Threads of the parallel method, as in the published experiments.
THREADS = 4
DAMPINGS = (0.5, 0.6, 0.7, 0.8, 0.85, 0.9, 0.95, 0.99)
SWEEP = "method string, c double, tol double, rounds int, visits long, seconds double, l1 double, bound double"
COMPARED = "method string, rounds int, visits long, seconds double, l1 double, linf double"


def parallel_visits(run: K.LocalRun, src: np.ndarray, dst: np.ndarray, threads: int = THREADS) -> float:
    """Edge visits on the longest way through a parallel run: the search on one thread, then per level the larger of its
    largest component and an even share of all, and an even share of the edges between components."""
    comp, level = run.part.component, run.part.level
    own = (comp[src] == comp[dst]) & (src != dst)
    cost = np.bincount(comp[src[own]], minlength=len(comp)).astype(float)
    for c, rounds in run.rounds.items():
        cost[c] *= rounds
    total = np.bincount(level, cost, level.max(initial=0) + 1) if len(level) else np.zeros(1)
    most = np.zeros_like(total)
    np.maximum.at(most, level, cost)
    return 2 * len(src) + float(np.maximum(most, total / threads).sum()) + float((~own).sum()) / threads


#: Methods of a sweep.
SWEPT = ("series", "levelwise_scc_cac", "levelwise_scc", "levelwise_parallel")


class _Edges:
    """What a sweep runs, over arrays of edges."""

    def __init__(self, n, s, t, p, w):
        self.args, self.n, self.m, self.s, self.t = (n, s, t, p, w), n, len(s), s, t

    def partition(self) -> K.LocalPartition:
        return K.local_partition(self.n, self.s, self.t)

    def series_stops(self, c, tolerances):
        return K.series_stops(*self.args, c, tolerances)

    def levelwise(self, c, tol, part, policy=None, **how) -> K.LocalRun:
        return K.levelwise_local(*self.args, c, tol, policy=policy, part=part, **how)

    by_policy = levelwise

    def parallel_visits(self, run) -> int:
        return int(parallel_visits(run, self.s, self.t))

    def solve(self, solver: str, *how, **more):
        return getattr(K, solver)(*self.args, *how, **more)


class _Classes:
    """The same over classes of targets. Sets of a level go their rounds together, whatever the threads."""

    def __init__(self, g: C.Classes, w: np.ndarray):
        self.g, self.w, self.n, self.m = g, w, g.n, g.m

    def partition(self) -> K.LocalPartition:
        return C.partition(self.g)

    def series_stops(self, c, tolerances):
        return C.series_stops(self.g, self.w, c, tolerances)

    def levelwise(self, c, tol, part, policy=None, kind="scc_cac", workers=1) -> C.Run:
        return C.levelwise(self.g, self.w, c, tol, kind, part, THREADS)

    def by_policy(self, c, tol, part, policy=None, kind="scc_cac", workers=1, merge_below=0) -> C.Run:
        return C.by_policy(self.g, self.w, c, tol, kind, part, policy, merge_below)

    def parallel_visits(self, run) -> int:
        return int(run.longest)

    def solve(self, solver: str, *how, **more):
        return getattr(C, solver)(self.g, self.w, *how, **more)


def _swept(x, tolerances, dampings, methods, errors: bool) -> pd.DataFrame:
    """The rows of a sweep over ``_Edges`` or ``_Classes``."""
    n, rows = x.n, []
    by_series = K.Policy(dense_below=0)
    start = time.perf_counter()
    part = x.partition() if errors or set(methods) != {"series"} else None
    search = time.perf_counter() - start  # done once, counted in every run
    for c in dampings:
        exact = x.levelwise(c, 1e-16, part).rank if errors else np.full(n, np.nan)
        if "series" in methods:
            for tol, (r, rounds, visits, took) in zip(tolerances, x.series_stops(c, tolerances)):
                rows.append(("series", c, tol, rounds, visits, took, np.abs(r - exact).sum(), M.error_bound_total(n, tol, c)))
        for tol in tolerances if part else ():
            bound = M.error_bound_total(int(part.multi.sum()), tol, c)
            for method, how in (("levelwise_scc_cac", {}), ("levelwise_scc", {"kind": "scc"}), ("levelwise_parallel", {"workers": THREADS})):
                if method not in methods:
                    continue
                start = time.perf_counter()
                run = x.levelwise(c, tol, part, by_series, **how)
                took = time.perf_counter() - start + search
                visits = x.parallel_visits(run) if method == "levelwise_parallel" else run.visits + 2 * x.m
                rows.append((method, c, tol, max(run.rounds.values(), default=0), visits, took, np.abs(run.rank - exact).sum(), bound))
    return pd.DataFrame(rows, columns=["method", "c", "tol", "rounds", "visits", "seconds", "l1", "bound"])


def sweep(g: Graph, tolerances=TOLERANCES, dampings=(0.85,), methods=SWEPT, errors: bool = True, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """Rounds (the most of any component), edge visits (search included), seconds, L1 error and its bound of the whole-graph series,
    of the level-by-level method on both partitions and of its parallel form (visits on its longest way), per
    tolerance and damping. Only ``methods`` are run; without ``errors`` l1 is null and nothing is iterated to the end for it.
    Over ``local_edges`` edges the graph goes to the task as classes of targets, if these win."""

    def make(vertices: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        vertices = vertices.sort_values("id")
        ids, s, t = numbered(vertices, edges)
        return _swept(_Edges(len(ids), s, t, edges["prob"].to_numpy(), vertices["weight"].to_numpy()), tolerances, dampings, methods, errors)

    got = classes(g, local_edges)
    if got is not None:
        return in_task(g.edges.sparkSession, lambda w, x: _swept(_Classes(x, w), tolerances, dampings, methods, errors), SWEEP, *got[1:])
    return in_one_task(g, make, SWEEP)


def _compared(x, c: float, tol: float) -> pd.DataFrame:
    """The rows of ``compare_methods`` over ``_Edges`` or ``_Classes``."""
    m, rows = x.m, []
    start = time.perf_counter()
    part = x.partition()
    search = time.perf_counter() - start  # done once, counted in every run
    exact = x.levelwise(c, 1e-16, part).rank

    def add(method: str, solve) -> None:
        start = time.perf_counter()
        rank, rounds, visits = solve()
        took, off = time.perf_counter() - start + (search if method.startswith("levelwise") else 0.0), np.abs(rank - exact)
        rows.append((method, rounds, visits, took, off.sum(), off.max(initial=0.0)))

    def whole(solver):
        *_, rank, rounds = x.solve(solver, c, tol)
        return rank, rounds, rounds * m

    def levels(**how):
        run = x.by_policy(c, tol, part, **how)
        return run.rank, max(run.rounds.values(), default=0), run.visits + 2 * m

    add("series", lambda: x.solve("solve_series", c, tol))
    add("adaptive", lambda: x.solve("solve_series", c, tol, freeze=tol))
    for name in ("jacobi", "gauss_seidel", "power"):
        add(name, lambda f=f"solve_{name}": whole(f))
    add("levelwise", levels)
    add("levelwise_parallel", lambda: levels(workers=THREADS))
    add("levelwise_scc", lambda: levels(kind="scc"))
    add("levelwise_merged", lambda: levels(merge_below=100))
    for name, policy in (("all_series", K.Policy(dense_below=0, acyclic="series")), ("no_dense", K.Policy(dense_below=0)), ("gauss_seidel", K.Policy(large="gauss_seidel")), ("adaptive", K.Policy(large="adaptive"))):
        add(f"levelwise_{name}", lambda q=policy: levels(policy=q))
    return pd.DataFrame(rows, columns=["method", "rounds", "visits", "seconds", "l1", "linf"])


def compare_methods(g: Graph, c: float = 0.85, tol: float = 1e-9, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """Every method and solver mix at one tolerance, against ranks iterated to the end, in one task; over ``local_edges`` edges by classes
    of targets, if these win."""

    def make(vertices: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        vertices = vertices.sort_values("id")
        ids, s, t = numbered(vertices, edges)
        return _compared(_Edges(len(ids), s, t, edges["prob"].to_numpy(), vertices["weight"].to_numpy()), c, tol)

    got = classes(g, local_edges)
    if got is not None:
        return in_task(g.edges.sparkSession, lambda w, x: _compared(_Classes(x, w), c, tol), COMPARED, *got[1:])
    return in_one_task(g, make, COMPARED)


def tail_check(g: Graph, stops=(5, 10, 20, 40, 80), c: float = 0.85) -> DataFrame:
    """(k, missing, bound): what the sum of the first k terms lacks, and c/(1-c) times the last term's norm."""

    def make(vertices: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        vertices, rows = vertices.sort_values("id"), []
        ids, s, t = numbered(vertices, edges)
        p, term = edges["prob"].to_numpy(), vertices["weight"].to_numpy().astype(float)
        total, so_far = K.levelwise_local(len(ids), s, t, p, term, c, 1e-16).rank.sum(), term.sum()
        for k in range(1, max(stops) + 1):
            term = np.bincount(t, c * p * term[s], len(ids))
            so_far += term.sum()
            if k in stops:
                rows.append((k, total - so_far, M.tail_bound(term.sum(), c)))
        return pd.DataFrame(rows, columns=["k", "missing", "bound"])

    return in_one_task(g, make, "k long, missing double, bound double")


def costs(swept: DataFrame, cost: str = "visits") -> DataFrame:
    """A sweep as (method, c, tol, cost), the form that slopes and break-even points take."""
    return swept.select("method", "c", "tol", F.col(cost).cast("double").alias("cost"))


def damping_ratios(swept: DataFrame, cost: str = "visits") -> DataFrame:
    """(c, ratio): the baseline's cost over the level-by-level method's."""
    cost_of = lambda method: F.max(F.when(F.col("method") == method, F.col(cost)))
    return swept.groupBy("c").agg((cost_of("series") / cost_of("levelwise_scc_cac")).alias("ratio"))


def visits_of(g: Graph, c: float = 0.85, tol: float = 1e-9, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """(method, c, tol, cost): edge visits at one tolerance, by a sweep in one task up to ``local_edges`` or where classes of targets win,
    by passes over packed edges above. Over ``MOST_VERTICES`` vertices, whose arrays are not sent to all tasks, one task takes the graph, whatever its size."""
    if g.edges.limit(local_edges + 1).count() <= local_edges or g.vertices.limit(MOST_VERTICES + 1).count() > MOST_VERTICES:
        return costs(sweep(g, (tol,), (c,), errors=False))
    got = classes(g, local_edges)
    if got is not None:
        return costs(in_task(g.edges.sparkSession, lambda w, x: _swept(_Classes(x, w), (tol,), (c,), SWEPT, False), SWEEP, *got[1:]))
    rows = [(method, c, tol, float(cost)) for method, cost in packed_visits(g, c, tol, THREADS, local_edges).items()]
    return g.edges.sparkSession.createDataFrame(rows, "method string, c double, tol double, cost double")


def copies_scale(one: Graph, ten: Graph, tol: float = 1e-9, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """(method, ratio) of edge visits, ten copies over one."""
    both = [visits_of(g, tol=tol, local_edges=local_edges).withColumn("copies", F.lit(k)) for g, k in ((one, 1), (ten, 10))]
    return M.scale_ratio(both[0].unionByName(both[1]))


def seconds_by_step(g: Graph, c: float = 0.85, tol: float = 1e-9, engine: str = "auto") -> DataFrame:
    """(run_id, step, seconds, detail): components, block layout and ranks, next to the whole-graph baseline."""
    log, spark = M.RunLog("levelwise"), g.edges.sparkSession
    with log.timed("components"):
        p = partition(g, engine)
        p = Partition(g, materialise(p.vertices, "partition"))
    with log.timed("layout"):
        materialise(plan_blocks(p), "blocks")
        materialise(classify_edges(p), "classes")
    with log.timed("ranks", c=c, tol=tol):
        materialise(R.levelwise_rank(g, c, tol, part=p, engine=engine), "ranks")
    with log.timed("baseline", c=c, tol=tol):
        materialise(R.series_rank(g, c, tol, engine=engine), "ranks")
    return log.frame(spark)
