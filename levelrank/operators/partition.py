"""Components and levels.

Three routes give the same partition. Graphs of up to ``LOCAL_EDGES`` edges go to one task's
kernel, larger ones as classes of targets with the same sources where these win (``twins``). Others are peeled: vertices without in- or out-edges leave in rounds; the
rest falls into strongly connected sets by colours (the smallest id that reaches a
vertex) and backward search inside a colour, until what is left fits kernels, one weak
component each. Levels are a longest-path fixpoint over contracted edges that cost 0
between single vertices and 1 otherwise; equal-level edges of cost 0 make the acyclic components.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.functions import compact as C
from levelrank.functions import kernels as K
from levelrank.operators.connect import connected_components
from levelrank.operators.model import LOCAL_EDGES, Graph, Partition
from levelrank.operators.twins import FEW_EDGES, classes, in_task
from levelrank.plans.staging import materialise

LABELS = "id long, component long, kind string, size long, level int, scc long, scc_level int"


def numbered(vertices: pd.DataFrame, edges: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(sorted ids, source places, target places)."""
    ids = np.sort(vertices["id"].to_numpy())
    return ids, np.searchsorted(ids, edges["src"].to_numpy()), np.searchsorted(ids, edges["dst"].to_numpy())


def in_one_task(g: Graph, make, schema: str) -> DataFrame:
    """``make(vertices, edges)`` over the whole graph in one task. The caller has checked the size."""
    v, e = (x.withColumn("task", F.lit(0)).groupBy("task") for x in (g.vertices, g.edges))
    return v.cogroup(e).applyInPandas(make, schema)


def _label(vertices: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
    ids, s, t = numbered(vertices, edges)
    return _labels(ids, K.local_partition(len(ids), s, t))


def _labels(ids: np.ndarray, p: K.LocalPartition) -> pd.DataFrame:
    size = np.bincount(p.component, minlength=len(ids))[p.component] if len(ids) else p.component
    return pd.DataFrame({"id": ids, "component": ids[p.component], "kind": np.where(p.multi, K.SCC, K.CAC), "size": size, "level": p.level.astype(np.int32), "scc": ids[p.scc], "scc_level": p.scc_level.astype(np.int32)})


# ---------------------------------------------------------------- strongly connected sets
def trim(vertices: DataFrame, edges: DataFrame, rounds: int = 16) -> tuple[DataFrame, DataFrame]:
    """Drop edges of vertices that lack in- or out-edges, round by round: (settled single ids, remaining edges)."""
    cur, n = edges, edges.count()
    for _ in range(rounds):
        live = cur.select(F.col("src").alias("id")).intersect(cur.select(F.col("dst").alias("id")))
        cur = materialise(cur.join(live.withColumnRenamed("id", "src"), "src", "left_semi").join(live.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst"), "trim")
        left = cur.count()
        if left in (0, n):
            break
        n = left
    on = cur.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    return vertices.select("id").join(on, "id", "left_anti"), cur


def _spread_min(edges: DataFrame, colours: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """Each vertex takes the smallest colour that reaches it; only changed vertices send."""
    cur, changed = colours, colours
    for _ in range(max_rounds):
        offers = edges.join(changed, edges.src == changed.id).groupBy("dst").agg(F.min("colour").alias("offer"))
        new = materialise(cur.join(offers, cur.id == offers.dst, "left").select("id", F.least("colour", F.coalesce("offer", "colour")).alias("colour"), (F.coalesce("offer", "colour") < F.col("colour")).alias("moved")), "colours")
        cur, changed = new.select("id", "colour"), new.where("moved").select("id", "colour")
        if changed.isEmpty():
            return cur
    raise RuntimeError("colours did not settle")


def _colour_pass(edges: DataFrame) -> DataFrame:
    """(id, scc) of the sets whose smallest reaching vertex lies in them: forward colours, then backward
    from each colour's own vertex inside the colour."""
    ids = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    colours = _spread_min(edges, materialise(ids.withColumn("colour", F.col("id")), "ids"))
    a, b = colours.select(F.col("id").alias("src"), F.col("colour").alias("ca")), colours.select(F.col("id").alias("dst"), F.col("colour").alias("cb"))
    within = materialise(edges.join(a, "src").join(b, "dst").where("ca = cb").select(F.col("dst").alias("src"), F.col("src").alias("dst"), "ca"), "within")
    found = front = colours.where("id = colour").select("id", F.col("colour").alias("scc"))
    while True:
        step = within.join(front, within.src == front.id).select(F.col("dst").alias("id"), "scc").distinct()
        front = materialise(step.join(found, "id", "left_anti"), "front")
        if front.isEmpty():
            return found
        found = materialise(found.unionByName(front), "found")


def scc(g: Graph, local_edges: int = LOCAL_EDGES, max_passes: int = 50) -> DataFrame:
    """(id, scc): smallest member of each vertex's strongly connected set, distributed."""
    vertices, edges = g.vertices.select("id"), materialise(g.edges.where("src <> dst").select("src", "dst"), "edges")
    done = None
    for _ in range(max_passes):
        single, edges = trim(vertices, edges)
        part = single.withColumn("scc", F.col("id"))
        n = edges.count()
        if 0 < n <= local_edges:
            part = part.unionByName(_tail(edges))
            n = 0
        done = part if done is None else done.unionByName(part)
        if not n:
            return done
        found = _colour_pass(edges)
        done = done.unionByName(found)
        left = found.select("id")
        edges = materialise(edges.join(left.withColumnRenamed("id", "src"), "src", "left_anti").join(left.withColumnRenamed("id", "dst"), "dst", "left_anti"), "rest")
        before = single.select("id").unionByName(left)
        vertices = materialise(vertices.join(before, "id", "left_anti"), "rest")
    raise RuntimeError("components did not settle")


def _tail(edges: DataFrame) -> DataFrame:
    """Kernels on the rest, one weak component a group."""
    weak = connected_components(edges.select(F.col("src").alias("a"), F.col("dst").alias("b")))

    def solve(block: pd.DataFrame) -> pd.DataFrame:
        ids = np.unique(block[["src", "dst"]].to_numpy())
        offsets, targets, _ = K.rows(len(ids), np.searchsorted(ids, block["src"]), np.searchsorted(ids, block["dst"]))
        return pd.DataFrame({"id": ids, "scc": ids[K.local_scc(offsets, targets)]})

    return edges.join(weak, edges.src == weak.id).select("component", "src", "dst").groupBy("component").applyInPandas(solve, "id long, scc long")


# ---------------------------------------------------------------- levels
def contract(edges: DataFrame, labels: DataFrame, label: str = "scc") -> DataFrame:
    """(a, b, n_edges): edges between different labels."""
    a, b = labels.select(F.col("id").alias("src"), F.col(label).alias("a")), labels.select(F.col("id").alias("dst"), F.col(label).alias("b"))
    return edges.join(a, "src").join(b, "dst").where("a <> b").groupBy("a", "b").agg(F.count("*").alias("n_edges"))


def relax(nodes: DataFrame, dag: DataFrame, max_rounds: int = 100_000) -> DataFrame:
    """(node, level): longest cost path below each node of a DAG (a, b, cost); only raised nodes send."""
    cur = changed = nodes.select("node", F.lit(0).alias("level"))
    for _ in range(max_rounds):
        offers = dag.join(changed, dag.b == changed.node).groupBy("a").agg(F.max(F.col("level") + F.col("cost")).alias("offer"), F.lit(True).alias("any"))
        new = materialise(cur.join(offers, cur.node == offers.a, "left").select("node", F.greatest("level", F.coalesce("offer", "level")).cast("int").alias("level"), (F.coalesce("offer", "level") > F.col("level")).alias("moved")), "levels")
        cur, changed = new.select("node", "level"), new.where("moved").select("node", "level")
        if changed.isEmpty():
            return cur
    raise RuntimeError("the contracted graph has a cycle")


def scc_levels(g: Graph, sets: DataFrame) -> DataFrame:
    dag = materialise(contract(g.edges, sets).select("a", "b", F.lit(1).alias("cost")), "dag")
    return relax(sets.select(F.col("scc").alias("node")).distinct(), dag)


def _distributed(g: Graph, local_edges: int) -> DataFrame:
    sets = materialise(scc(g, local_edges), "scc")
    size = sets.groupBy("scc").agg((F.count("*") > 1).alias("multi"))
    dag = contract(g.edges, sets).join(size.select(F.col("scc").alias("a"), F.col("multi").alias("ma")), "a").join(size.select(F.col("scc").alias("b"), F.col("multi").alias("mb")), "b")
    dag = materialise(dag.select("a", "b", F.when(F.col("ma") | F.col("mb"), 1).otherwise(0).alias("cost")), "dag")
    nodes = materialise(size.withColumnRenamed("scc", "node"), "nodes")
    level = materialise(relax(nodes, dag), "level")
    plain = materialise(relax(nodes, dag.withColumn("cost", F.lit(1))), "plain")
    la, lb = level.select(F.col("node").alias("a"), F.col("level").alias("x")), level.select(F.col("node").alias("b"), F.col("level").alias("y"))
    joined = dag.where("cost = 0").join(la, "a").join(lb, "b").where("x = y").select("a", "b")
    groups = connected_components(joined)
    labels = nodes.join(level, "node").join(plain.withColumnRenamed("level", "scc_level"), "node").join(groups.withColumnRenamed("id", "node"), "node", "left")
    labels = labels.select(F.col("node").alias("scc"), F.coalesce("component", "node").alias("component"), F.when(F.col("multi"), K.SCC).otherwise(K.CAC).alias("kind"), "level", "scc_level")
    out = sets.join(labels, "scc")
    return out.join(out.groupBy("component").agg(F.count("*").alias("size")), "component").select("id", "component", "kind", "size", "level", "scc", "scc_level")


def partition(g: Graph, engine: str = "auto", local_edges: int = LOCAL_EDGES) -> Partition:
    if engine == "auto":
        engine = "local" if g.edges.limit(local_edges + 1).count() <= local_edges else "distributed"
        got = classes(g, max(local_edges, FEW_EDGES)) if engine == "distributed" else None
        if got is not None:  # one task holds the members of the classes
            return Partition(g, materialise(in_task(g.edges.sparkSession, lambda ids, w, x: _labels(ids, C.partition(x)), LABELS, *got), "partition"))
    if engine == "local":
        return Partition(g, in_one_task(g, _label, LABELS))
    return Partition(g, materialise(_distributed(g, local_edges), "partition"))


def merge_bottom_up(n: int, edges: list[tuple[int, int]], seed: int) -> tuple[list[int], list[frozenset]]:
    """The partition as a game of merges in random order: a single vertex joins its highest
    neighbours while none of them is a cycle. For tests on small graphs."""
    rng = np.random.default_rng(seed)
    src, dst = (np.array([e[k] for e in edges if e[0] != e[1]], np.int64) for k in (0, 1))
    base = K.local_partition(n, src, dst)
    group = {v: frozenset(np.flatnonzero(base.scc == base.scc[v]).tolist()) for v in range(n)}
    cycle = {v: bool(base.multi[v]) for v in range(n)}

    def levels() -> dict[frozenset, int]:
        out: dict[frozenset, int] = {}

        def of(c: frozenset) -> int:
            if c not in out:
                out[c] = 1 + max((of(group[t]) for s, t in zip(src.tolist(), dst.tolist()) if s in c and t not in c), default=-1)
            return out[c]

        for v in range(n):
            of(group[v])
        return out

    while True:
        lv, moves = levels(), []
        for v in range(n):
            if cycle[v]:
                continue
            near = {group[t] for s, t in zip(src.tolist(), dst.tolist()) if s == v and group[t] != group[v]}
            # the vertex may move down only if its own component does not hold it up from below
            inside = [t for s, t in zip(src.tolist(), dst.tolist()) if s == v and group[t] == group[v]]
            if near and not inside:
                top = max(lv[c] for c in near)
                high = [c for c in near if lv[c] == top]
                if not any(cycle[next(iter(c))] for c in high) and lv[group[v]] == top + 1:
                    moves.append((v, high))
        if not moves:
            return [lv[group[v]] for v in range(n)], sorted(set(group.values()), key=min)
        low = min(lv[group[v]] for v, _ in moves)
        moves = [m for m in moves if lv[group[m[0]]] == low]
        v, high = moves[rng.integers(len(moves))]
        merged = frozenset().union(group[v], *high)
        for u in merged:
            group[u] = merged
