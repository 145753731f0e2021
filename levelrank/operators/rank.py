"""Rank methods: level by level, the whole-graph baselines, and the forms around them.

All results are (id, rank), non-normalised: R = W + c * transposed probabilities * R. ``engine='auto'`` runs
one task's kernels up to ``LOCAL_EDGES`` edges and frames above; both can be asked for. ``levelwise_rank`` also has 'packed'
between them, for graphs whose vertices fit arrays of the driver.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.functions import compact as C
from levelrank.functions import kernels as K
from levelrank.operators.model import LOCAL_EDGES, Graph, Partition
from levelrank.operators.packed import HELD_EDGES, MOST_VERTICES, packed_ranks
from levelrank.operators.partition import in_one_task, numbered, partition
from levelrank.operators.series import acyclic_distributed, gauss_seidel_distributed, round_bound, series_distributed
from levelrank.operators.twins import classes, in_task
from levelrank.plans.blocks import MAX_LEVELS, classify_edges, merged_partition, plan_blocks, scc_partition
from levelrank.plans.staging import materialise, small_rows

RANKS = "id long, rank double"


def _engine(g: Graph, engine: str, local_edges: int) -> str:
    if engine != "auto":
        return engine
    return "local" if g.edges.limit(local_edges + 1).count() <= local_edges else "distributed"


def local_ranks(g: Graph, solve: Callable) -> DataFrame:
    """``solve(n, src, dst, prob, weight) -> rank`` over the whole graph in one task."""

    def make(vertices: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        vertices = vertices.sort_values("id")
        ids, s, t = numbered(vertices, edges)
        return pd.DataFrame({"id": ids, "rank": solve(len(ids), s, t, edges["prob"].to_numpy(), vertices["weight"].to_numpy())})

    return in_one_task(g, make, RANKS)


def one_task(g: Graph, vertices: int | None = None, local_edges: int = LOCAL_EDGES) -> Graph:
    """``g``, if one task takes it; otherwise an error that says so."""
    if g.edges.limit(local_edges + 1).count() > local_edges:
        raise ValueError(f"this form takes graphs of up to {local_edges} edges")
    if vertices is not None and g.vertices.limit(vertices + 1).count() > vertices:
        raise ValueError(f"this form takes graphs of up to {vertices} vertices")
    return g


# ---------------------------------------------------------------- whole graph
def push(ranks: DataFrame, edges: DataFrame, c: float) -> DataFrame:
    """(id, gain): one scatter of ranks along edges, summed in tasks before the shuffle."""
    return edges.join(ranks, edges.src == ranks.id).select(F.col("dst").alias("id"), (c * F.col("prob") * F.col("rank")).alias("gain")).groupBy("id").agg(F.sum("gain").alias("gain"))


def series_rank(g: Graph, c: float = 0.85, tol: float = 1e-9, engine: str = "auto", freeze: bool = False, local_edges: int = LOCAL_EDGES, max_rounds: int | None = None) -> DataFrame:
    """Baseline: the whole graph as one component, by power series; ``freeze`` stops converged vertices. Raises
    ``Unfinished`` if ``max_rounds`` end before the tolerance."""
    if _engine(g, engine, local_edges) == "local":
        return local_ranks(g, lambda n, s, t, p, w: K.solve_series(n, s, t, p, w, c, tol, max_rounds or K.MAX_ROUNDS, tol if freeze else 0.0)[0])
    return series_distributed(g.vertices, g.edges, c, tol, max_rounds, freeze)[0]


def power_rank(g: Graph, c: float = 0.85, tol: float = 1e-12, engine: str = "auto", local_edges: int = LOCAL_EDGES, max_rounds: int | None = None) -> DataFrame:
    """Baseline: power iteration on the normalised form: (id, rank, rank_norm)."""
    if _engine(g, engine, local_edges) == "local":

        def make(vertices: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
            vertices = vertices.sort_values("id")
            ids, s, t = numbered(vertices, edges)
            x, r, _ = K.solve_power(len(ids), s, t, edges["prob"].to_numpy(), vertices["weight"].to_numpy(), c, tol, max_rounds or K.MAX_ROUNDS)
            return pd.DataFrame({"id": ids, "rank": r, "rank_norm": x})

        return in_one_task(g, make, RANKS + ", rank_norm double")
    edges, total = materialise(g.edges, "edges"), g.vertices.agg(F.sum("weight")).first()[0]
    start = materialise(g.vertices.select("id", (F.col("weight") / total).alias("w")), "start")
    x, change, lost = start.select("id", F.col("w").alias("rank")), np.inf, 1.0
    for _ in range(max_rounds or round_bound(c, tol)):
        moved = start.join(push(x, edges, c), "id", "left").select("id", "w", F.coalesce("gain", F.lit(0.0)).alias("y"))
        moved = materialise(moved, "power")
        lost = 1 - (moved.agg(F.sum("y")).first()[0] or 0.0)
        new = materialise(moved.join(x, "id").select("id", (F.col("y") + lost * F.col("w")).alias("new"), "rank"), "power")
        change = new.agg(F.max(F.abs(F.col("new") - F.col("rank")))).first()[0] or 0.0
        x = new.select("id", F.col("new").alias("rank"))
        if change <= max(tol, 1e-16):
            break
    else:
        raise K.Unfinished(f"power iteration is not at {tol}")
    return x.select("id", (F.col("rank") * total / lost).alias("rank"), F.col("rank").alias("rank_norm"))


def local_variant(g: Graph, method: str, c: float = 0.85, tol: float = 1e-12, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """Block solvers over the whole graph in one task, whatever its size: jacobi, gauss_seidel, dense, hits. Memory follows the
    edges, of the dense forms the square of the vertices; jacobi has ``series_rank`` for frames and gauss_seidel ``gauss_seidel_rank``.
    Over ``local_edges`` edges the members of classes of targets stand for the edges, and the classes for the vertices, where these win."""
    solve = {"jacobi": lambda *a: K.solve_jacobi(*a, c, tol)[0], "gauss_seidel": lambda *a: K.solve_gauss_seidel(*a, c, tol)[0], "dense": lambda *a: K.solve_dense(*a, c), "hits": lambda *a: K.solve_hits(*a, c)}[method]
    over = {"jacobi": lambda x, w: C.solve_jacobi(x, w, c, tol)[0], "gauss_seidel": lambda x, w: C.solve_gauss_seidel(x, w, c, tol)[0], "dense": lambda x, w: C.solve_dense(x, w, c), "hits": lambda x, w: C.solve_hits(x, w, c)}[method]
    got = classes(g, local_edges)
    if got is not None and (method in ("jacobi", "gauss_seidel") or got[2].k <= K.DENSE_VERTICES):
        return in_task(g.edges.sparkSession, lambda ids, w, x: pd.DataFrame({"id": ids, "rank": over(x, w)}), RANKS, *got)
    return local_ranks(g, solve)


def gauss_seidel_rank(g: Graph, c: float = 0.85, tol: float = 1e-12, engine: str = "auto", local_edges: int = LOCAL_EDGES, parts: int = 8) -> DataFrame:
    """Sweeps with the newest values: vertex by vertex in one task, in ``parts`` groups of vertices on frames."""
    if _engine(g, engine, local_edges) == "local":
        return local_ranks(g, lambda *a: K.solve_gauss_seidel(*a, c, tol)[0])
    return gauss_seidel_distributed(g.vertices, g.edges, c, tol, parts)[0]


# ---------------------------------------------------------------- level by level
WORKERS = 4


def levelwise_rank(g: Graph, c: float = 0.85, tol: float = 1e-9, *, parallel: bool = True, kind: str = "scc_cac", engine: str = "auto", loops: str = "drop", policy: K.Policy | None = None, merge_below: int = 0, handover: str = "level", stop_level: int = 0, local_edges: int = LOCAL_EDGES, bin_edges: int = 500_000, part: Partition | None = None) -> DataFrame:
    """Ranks component by component, highest level first.

    Every option holds on both routes. Locally one task walks all levels, the components of a level one by one or,
    with ``parallel``, by ``WORKERS`` threads. On frames every level is a few jobs: single vertices by an expression,
    blocks in bins of kernels (``parallel``: one task per bin, otherwise one for the level), components over
    ``local_edges`` by the distributed solvers, then a scatter to the levels below. ``kind`` 'scc' takes strongly
    connected sets and their levels alone, ``merge_below`` joins runs of small levels, ``handover`` is 'level'
    (a scatter per level), 'component' (one per solved part) or 'pull' (a level gathers all it gets from above).
    ``engine`` 'auto' takes graphs over the limit as classes of targets with the same sources where these win, for the plain form.
    ``engine`` 'packed' takes graphs of up to ``HELD_EDGES`` edges and ``MOST_VERTICES`` vertices by passes over packed edges and
    any other as 'auto'; it knows none of the options but ``c``, ``tol`` and ``local_edges``."""
    if kind not in ("scc_cac", "scc") or handover not in ("level", "component", "pull"):
        raise ValueError("kind is scc_cac or scc, handover level, component or pull")
    if engine == "packed":
        if (kind, loops, policy, merge_below, handover, stop_level, part) != ("scc_cac", "drop", None, 0, "level", 0, None):
            raise ValueError("packed edges take no other form of the method")
        engine = "auto"
        if local_edges < g.edges.limit(HELD_EDGES + 1).count() <= HELD_EDGES and g.vertices.limit(MOST_VERTICES + 1).count() <= MOST_VERTICES:
            return packed_ranks(g, c, tol, local_edges)
    if _engine(g, engine, local_edges) == "local":
        return local_ranks(g, lambda n, s, t, p, w: K.levelwise_local(n, s, t, p, w, c, tol, kind, loops, policy, merge_below, handover, stop_level, WORKERS if parallel else 1).rank)
    if engine == "auto" and (loops, policy, merge_below, handover, stop_level, part) == ("drop", None, 0, "level", 0, None):
        got = classes(g, local_edges)
        if got is not None:
            return in_task(g.edges.sparkSession, lambda ids, w, x: pd.DataFrame({"id": ids, "rank": C.levelwise(x, w, c, tol, kind).rank}), RANKS, *got)
    p = part or partition(g, local_edges=local_edges)
    if kind == "scc":
        p = scc_partition(p)
    if merge_below:
        p = merged_partition(p, merge_below)
    return levelwise_distributed(p, c, tol, parallel=parallel, loops=loops, policy=policy, local_edges=local_edges, bin_edges=bin_edges, handover=handover, stop_level=stop_level)[0]


#: Written gains of levels that may wait before they are summed into one.
WAITING = 12
LOCAL_SOLVERS, FAR_SOLVERS = ("acyclic", "dense", "series_local"), ("series_distributed", "acyclic_distributed")


def levelwise_distributed(p: Partition, c: float, tol: float, *, parallel: bool = True, loops: str = "drop", policy: K.Policy | None = None, local_edges: int = LOCAL_EDGES, bin_edges: int = 500_000, handover: str = "level", stop_level: int = 0) -> tuple[DataFrame, list[dict]]:
    """(ranks, one log row per level): the frame route of ``levelwise_rank``.

    What a level hands down is written once, by target and level; the start weights are never rewritten. A level
    reads its own weights and the gains for it, and gains are summed into one table every ``WAITING`` levels."""
    policy = policy or K.Policy()
    plan = materialise(plan_blocks(p, policy, local_edges, bin_edges if parallel else 1 << 60), "plan")
    edges = materialise(classify_edges(p).sortWithinPartitions("src_level"), "classes")
    v = p.vertices.join(plan.select("component", "solver", "bin"), "component").select("id", "component", "level", "solver", "bin")
    loop = edges.where("edge_class = 'loop'").select(F.col("src").alias("id"), F.col("prob").alias("loop")) if loops == "keep" else None
    w = p.graph.vertices.select("id", F.col("weight").alias("w")).join(v, "id")
    w = w.join(loop, "id", "left").fillna(0.0, ["loop"]) if loop is not None else w.withColumn("loop", F.lit(0.0))
    start = materialise(w.sortWithinPartitions("level"), "weights")
    between, inside = edges.where("edge_class = 'between'"), edges.where("edge_class = 'inside'")
    local, far = F.col("solver").isin(*LOCAL_SOLVERS), F.col("solver").isin(*FAR_SOLVERS)
    counts = plan.groupBy("level").agg(F.count_if(F.col("solver") == "single").alias("single"), F.count_if(local).alias("block"), F.count_if(F.col("solver") == "series_distributed").alias("large"), F.count_if(F.col("solver") == "acyclic_distributed").alias("forest"))
    profile = small_rows(counts.orderBy(F.desc("level")), MAX_LEVELS, "levels")
    handed: list[DataFrame] = []
    ranks: list[DataFrame] = []
    log = []

    def solve(key, vertices: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        vertices = vertices.sort_values("id")
        ids, s, t = numbered(vertices, e)
        prob, n = e["prob"].to_numpy(), len(ids)
        hold = np.flatnonzero(vertices["loop"].to_numpy() > 0)
        s, t, prob = np.r_[s, hold], np.r_[t, hold], np.r_[prob, vertices["loop"].to_numpy()[hold]]
        comp = np.unique(vertices["component"].to_numpy(), return_inverse=True)[1]
        rank = K.solve_components(n, s.astype(np.int64), t.astype(np.int64), prob, vertices["w"].to_numpy(), c, tol, comp, vertices["solver"].to_numpy(), policy)
        return pd.DataFrame({"id": ids, "rank": rank})

    def hand_down(part: DataFrame, level: int) -> None:
        sent = between.where(F.col("src_level") == level).join(part, F.col("src") == F.col("id"))
        gain = sent.select(F.col("dst").alias("to"), F.col("dst_level").alias("to_level"), (c * F.col("prob") * F.col("rank")).alias("gain"))
        handed.append(materialise(gain.groupBy("to", "to_level").agg(F.sum("gain").alias("gain")), "gains"))
        if len(handed) > WAITING:
            handed[:] = [materialise(all_of(handed).groupBy("to", "to_level").agg(F.sum("gain").alias("gain")), "gains")]

    def weights(level: int) -> DataFrame:
        here = start.where(F.col("level") == level)
        if handover == "pull":
            if not ranks:
                return here
            e = between.where(F.col("dst_level") == level).join(all_of(ranks), F.col("src") == F.col("id"))
            got = e.groupBy(F.col("dst").alias("to")).agg(F.sum(c * F.col("prob") * F.col("rank")).alias("gain"))
        elif not handed:
            return here
        else:
            got = all_of(handed).where(F.col("to_level") == level).groupBy("to").agg(F.sum("gain").alias("gain"))
        return here.join(got, here["id"] == got["to"], "left").withColumn("w", F.col("w") + F.coalesce("gain", F.lit(0.0))).drop("to", "gain")

    for r in profile:
        if r.level < stop_level:
            break
        here, parts, rounds = materialise(weights(r.level), "level"), [], 0
        if r.single:
            parts.append(here.where("solver = 'single'").select("id", (F.col("w") / (1 - c * F.col("loop"))).alias("rank")))
        if r.block:
            bins = plan.where((F.col("level") == r.level) & local).select(F.col("component").alias("src_component"), "bin")
            block = here.where(local).select("bin", "id", "component", "solver", "w", "loop")
            e = inside.where(F.col("src_level") == r.level).join(bins, "src_component").select("bin", "src", "dst", "prob")
            parts.append(block.groupBy("bin").cogroup(e.groupBy("bin")).applyInPandas(solve, RANKS))
        for solver, n in (("series_distributed", r.large), ("acyclic_distributed", r.forest)):
            if n:
                big = here.where(F.col("solver") == solver).select("id", F.col("w").alias("weight"), "loop")
                e = inside.where(F.col("src_level") == r.level).join(big.select(F.col("id").alias("src")), "src", "left_semi").select("src", "dst", "prob")
                held = big.where("loop > 0").select(F.col("id").alias("src"), F.col("id").alias("dst"), F.col("loop").alias("prob"))
                if solver == "acyclic_distributed":
                    got, rounds = acyclic_distributed(big, e, c)
                elif policy.large == "gauss_seidel":
                    got, rounds = gauss_seidel_distributed(big.select("id", "weight"), e.unionByName(held), c, tol)
                else:
                    got, rounds = series_distributed(big, e.unionByName(held), c, tol, freeze=policy.large == "adaptive")
                parts.append(got)
        if handover == "component":
            parts = [materialise(x, "ranks") for x in parts]
            for x in parts:
                hand_down(x, r.level)
            ranks += parts
        else:
            level = materialise(all_of(parts), "ranks")
            ranks.append(level)
            if handover == "level" and r.level:
                hand_down(level, r.level)
        log.append({"level": r.level, "single": r.single, "block": r.block, "large": r.large + r.forest, "rounds": rounds})
    if stop_level:  # weights handed down so far
        got = all_of(handed).groupBy("to").agg(F.sum("gain").alias("gain")) if handed else None
        if handover == "pull" and ranks:
            got = between.join(all_of(ranks), F.col("src") == F.col("id")).groupBy(F.col("dst").alias("to")).agg(F.sum(c * F.col("prob") * F.col("rank")).alias("gain"))
        rest = start.where(F.col("level") < stop_level)
        rest = rest.join(got, rest["id"] == got["to"], "left").select("id", (F.col("w") + F.coalesce("gain", F.lit(0.0))).alias("rank")) if got is not None else rest.select("id", F.col("w").alias("rank"))
        ranks.append(rest)
    return (all_of(ranks) if ranks else p.graph.vertices.select("id", F.col("weight").alias("rank"))), log


def all_of(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for x in frames[1:]:
        out = out.unionByName(x)
    return out


# ---------------------------------------------------------------- related baselines
def dangling_last(g: Graph, c: float = 0.85, tol: float = 1e-12, **how) -> DataFrame:
    """Vertices without out-edges leave; their ranks are one scatter at the end."""
    sources = g.edges.select(F.col("src").alias("id")).distinct()
    core = g.vertices.join(sources, "id", "left_semi")
    kept = g.edges.join(sources.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst", "prob")
    ranks = materialise(series_rank(Graph(core, kept), c, tol, **how), "core")
    rest = g.vertices.join(sources, "id", "left_anti").join(push(ranks, g.edges, c), "id", "left")
    return ranks.unionByName(rest.select("id", (F.col("weight") + F.coalesce("gain", F.lit(0.0))).alias("rank")))


def roots_first(g: Graph, c: float = 0.85, tol: float = 1e-12, **how) -> DataFrame:
    """Vertices without in-edges keep their weight and hand it on before the rest is solved."""
    targets = g.edges.select(F.col("dst").alias("id")).distinct()
    roots = g.vertices.join(targets, "id", "left_anti").select("id", F.col("weight").alias("rank"))
    rest = g.vertices.join(targets, "id", "left_semi").join(push(roots, g.edges, c), "id", "left").select("id", (F.col("weight") + F.coalesce("gain", F.lit(0.0))).alias("weight"))
    kept = g.edges.join(targets.withColumnRenamed("id", "src"), "src", "left_semi").select("src", "dst", "prob")
    return roots.unionByName(series_rank(Graph(rest, kept), c, tol, **how))


def recursive_dangling(g: Graph, c: float = 0.85, tol: float = 1e-12, max_rounds: int = 100_000) -> DataFrame:
    """Dangling vertices are peeled until none is left; the core is solved, then the peeled ones in
    reverse order, each wave by one scatter."""
    cur_v, cur_e, waves = materialise(g.vertices, "core"), materialise(g.edges, "core"), []
    for _ in range(max_rounds):
        sources = cur_e.select(F.col("src").alias("id")).distinct()
        wave = materialise(cur_v.join(sources, "id", "left_anti"), "wave")
        if wave.isEmpty():
            break
        waves.append(wave)
        cur_v = materialise(cur_v.join(sources, "id", "left_semi"), "core")
        cur_e = materialise(cur_e.join(sources.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst", "prob"), "core")
    ranks = materialise(series_rank(Graph(cur_v, cur_e), c, tol), "ranks")
    for wave in reversed(waves):
        into = g.edges.join(wave.select(F.col("id").alias("dst")), "dst", "left_semi")  # no other edge is read further
        got = wave.join(push(ranks, into, c), "id", "left").select("id", (F.col("weight") + F.coalesce("gain", F.lit(0.0))).alias("rank"))
        ranks = materialise(ranks.unionByName(got), "ranks")
    return ranks


def aggregated_rank(g: Graph, groups: DataFrame, c: float = 0.85, tol: float = 1e-12, sweeps: int = 1) -> DataFrame:
    """Approximate: ranks of the graph of groups (id, grp), shared within a group by start weight, then ``sweeps`` plain steps."""
    v = materialise(g.vertices.join(groups, "id"), "groups")
    a, b = v.select(F.col("id").alias("src"), F.col("grp").alias("ga"), F.col("weight").alias("wa")), v.select(F.col("id").alias("dst"), F.col("grp").alias("gb"))
    total = v.groupBy("grp").agg(F.sum("weight").alias("weight"))
    up = g.edges.join(a, "src").join(b, "dst").join(total.withColumnRenamed("grp", "ga"), "ga").where("weight > 0").groupBy(F.col("ga").alias("src"), F.col("gb").alias("dst")).agg(F.sum(F.col("prob") * F.col("wa") / F.col("weight")).alias("prob"))
    top = series_rank(Graph(total.select(F.col("grp").alias("id"), "weight"), up), c, tol).withColumnRenamed("id", "grp")
    ranks = v.join(top, "grp").join(total.withColumnRenamed("weight", "all"), "grp").select("id", (F.col("rank") * F.col("weight") / F.col("all")).alias("rank"))
    for _ in range(sweeps):
        ranks = materialise(g.vertices.join(push(ranks, g.edges, c), "id", "left").select("id", (F.col("weight") + F.coalesce("gain", F.lit(0.0))).alias("rank")), "sweep")
    return ranks


def solve_permuted(g: Graph, c: float = 0.85, tol: float = 1e-12, kind: str = "scc_cac") -> DataFrame:
    """The whole system in block-triangular order, by sweeps that use the newest values: levels from the top, so
    edges between components carry final values after one sweep. In one task, whatever the size."""

    def solve(n, s, t, p, w):
        part = K.local_partition(n, s, t)
        level, comp = (part.level, part.component) if kind == "scc_cac" else (part.scc_level, part.scc)
        order = np.lexsort((np.arange(n), comp, -level))
        place = np.empty(n, np.int64)
        place[order] = np.arange(n)
        x, _ = K.solve_gauss_seidel(n, place[s], place[t], p, w[order], c, tol)
        return x[place]

    return local_ranks(g, solve)


# ---------------------------------------------------------------- forms around the methods
def remove_vertex(g: Graph, vertex: int, rank: float, c: float = 0.85) -> Graph:
    """The graph without a vertex that nothing it reaches leads back to; its rank is folded into start weights."""
    out = g.edges.where((F.col("src") == vertex) & (F.col("dst") != vertex)).select(F.col("dst").alias("id"), (c * F.col("prob") * rank).alias("gain"))
    v = g.vertices.where(F.col("id") != vertex).join(out, "id", "left").select("id", (F.col("weight") + F.coalesce("gain", F.lit(0.0))).alias("weight"))
    return Graph(v, g.edges.where((F.col("src") != vertex) & (F.col("dst") != vertex)))


def levelwise_solve(coefficients: DataFrame, right: DataFrame, tol: float = 1e-12, **how) -> DataFrame:
    """x = b + Mx for any M with column sums under 1: rows (src, dst, prob) say how much of x[src] flows to x[dst]."""
    return levelwise_rank(Graph(right, coefficients), 1.0, tol, **how)


def walk_rank(g: Graph, walks: int = 20, c: float = 0.85, seed: int = 7, max_steps: int = 100_000) -> DataFrame:
    """Monte-Carlo: ``walks`` walkers per vertex, each worth its weight over ``walks``; every visit counts.

    Choices are hashes of walker and step, so reruns agree. A step is a range join on the cumulated probabilities of a source."""
    from pyspark.sql import Window

    upto = F.sum("prob").over(Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, 0))
    table = materialise(g.edges.withColumn("hi", upto).withColumn("lo", F.col("hi") - F.col("prob")).select("src", "dst", "lo", "hi"), "table")
    cur = materialise(g.vertices.select("id", F.explode(F.sequence(F.lit(1), F.lit(walks))).alias("k"), (F.col("weight") / walks).alias("worth"), F.col("id").alias("at")), "walkers")
    visits = [cur.groupBy(F.col("at").alias("id")).agg(F.sum("worth").alias("rank"))]
    draw = lambda step, salt: F.pmod(F.xxhash64("id", "k", F.lit(step), F.lit(salt), F.lit(seed)), F.lit(1 << 40)) / float(1 << 40)
    for step in range(max_steps):
        going = cur.withColumn("u", draw(step, 1)).where(draw(step, 2) < c)
        cur = materialise(going.join(table, (going["at"] == table.src) & (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi"))).select("id", "k", "worth", F.col("dst").alias("at")), "walkers")
        if cur.isEmpty():
            break
        if step == max_steps - 1:
            raise K.Unfinished(f"walkers are still under way after {max_steps} steps")
        visits.append(cur.groupBy(F.col("at").alias("id")).agg(F.sum("worth").alias("rank")))
    out = visits[0]
    for x in visits[1:]:
        out = out.unionByName(x)
    return out.groupBy("id").agg(F.sum("rank").alias("rank"))


def update_rank(old: Graph, ranks: DataFrame, new: Graph, c: float = 0.85, tol: float = 1e-12, max_rounds: int = 100_000, **how) -> DataFrame:
    """Ranks after edges changed: only what changed sources reach is solved again. Ranks above are not touched by
    what happens below, so they stay and hand their weight into the cone."""
    gone = old.edges.select("src", "dst", "prob").exceptAll(new.edges.select("src", "dst", "prob"))
    come = new.edges.select("src", "dst", "prob").exceptAll(old.edges.select("src", "dst", "prob"))
    fresh = new.vertices.join(old.vertices, ["id", "weight"], "left_anti").select("id")
    cone = front = materialise(gone.select(F.col("dst").alias("id")).union(come.select(F.col("dst").alias("id"))).union(fresh).distinct(), "cone")
    if _engine(new, how.get("engine", "auto"), how.get("local_edges", LOCAL_EDGES)) == "local":
        cone = materialise(in_one_task(Graph(front, new.edges), _reached, "id long"), "cone")
    else:
        both = materialise(new.edges.select("src", "dst"), "edges")
        for _ in range(max_rounds):
            front = materialise(both.join(front, both.src == front.id, "left_semi").select(F.col("dst").alias("id")).distinct().join(cone, "id", "left_anti"), "front")
            if front.isEmpty():
                break
            cone = materialise(cone.union(front), "cone")
    kept = ranks.join(new.vertices, "id", "left_semi").join(cone, "id", "left_anti")
    inside = new.edges.join(cone.withColumnRenamed("id", "dst"), "dst", "left_semi")
    gain = push(kept, inside, c)
    weights = new.vertices.join(cone, "id", "left_semi").join(gain, "id", "left").select("id", (F.col("weight") + F.coalesce("gain", F.lit(0.0))).alias("weight"))
    within = inside.join(cone.withColumnRenamed("id", "src"), "src", "left_semi").select("src", "dst", "prob")
    return kept.select("id", "rank").unionByName(levelwise_rank(Graph(weights, within), c, tol, **how))


def _reached(start: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
    """All that edges lead to from the start, which is included."""
    ids = np.unique(np.r_[start["id"].to_numpy(), edges["src"].to_numpy(), edges["dst"].to_numpy()]).astype(np.int64)
    offsets, targets, _ = K.rows(len(ids), np.searchsorted(ids, edges["src"].to_numpy()), np.searchsorted(ids, edges["dst"].to_numpy()))
    seen = np.zeros(len(ids), bool)
    front = np.searchsorted(ids, start["id"].to_numpy())
    while len(front):
        seen[front] = True
        sizes = offsets[front + 1] - offsets[front]
        near = np.unique(targets[np.repeat(offsets[front] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())])
        front = near[~seen[near]]
    return pd.DataFrame({"id": ids[seen]})
