"""The intermediate step: order, classify, pack and permute components."""

from __future__ import annotations

from collections import Counter

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelrank.functions.kernels import Policy
from levelrank.operators.model import Graph, Partition
from levelrank.plans.staging import materialise, small_rows

MAX_LEVELS = 1_000_000


def component_table(p: Partition) -> DataFrame:
    return p.vertices.groupBy("component", "kind", "size", "level").agg(F.count("*").alias("n")).drop("n")


def level_profile(p: Partition) -> DataFrame:
    """(level, n_vertices, n_components, n_scc, n_single, largest)."""
    c = component_table(p)
    return c.groupBy("level").agg(F.sum("size").alias("n_vertices"), F.count("*").alias("n_components"), F.count_if(F.col("kind") == "scc").alias("n_scc"), F.count_if(F.col("size") == 1).alias("n_single"), F.max("size").alias("largest"))


#: Rows of a range partition whose running sums one task adds up.
RANGE_ROWS = 1_000_000


def running(df: DataFrame, order: list[Column], cost: str, rows: int = RANGE_ROWS) -> DataFrame:
    """``df`` with ``place`` (rows before) and ``before`` (sum of ``cost`` before) in a total order: sums inside range
    partitions plus those of the partitions before, so no window sees more than a range."""
    parts = max(1, -(-df.count() // rows))
    named = [c.alias(f"_o{i}") for i, c in enumerate(order)]
    keys = [F.col(f"_o{i}") for i in range(len(order))]
    ranged = materialise(df.select("*", *named).repartitionByRange(parts, *keys).withColumn("_part", F.spark_partition_id()), "ranges")
    sums = small_rows(ranged.groupBy("_part").agg(F.count("*").alias("n"), F.sum(cost).alias("s")).orderBy("_part"), MAX_LEVELS, "ranges")
    starts, n, total = [], 0, 0
    for r in sums:
        starts.append((r["_part"], n, total))
        n, total = n + r.n, total + r.s
    table = df.sparkSession.createDataFrame(starts, "_part int, _n long, _s long")
    own = Window.partitionBy("_part").orderBy(*keys)
    placed = ranged.withColumn("_k", F.row_number().over(own) - 1).withColumn("_b", F.sum(cost).over(own.rowsBetween(Window.unboundedPreceding, 0)) - F.col(cost))
    return placed.join(F.broadcast(table), "_part").select(*df.columns, (F.col("_k") + F.col("_n")).cast("long").alias("place"), (F.col("_b") + F.col("_s")).cast("long").alias("before"))


def order_components(p: Partition) -> DataFrame:
    """(component, level, size, ordinal, first): highest level first, largest first in a level."""
    c = component_table(p).select("component", "level", "size")
    return running(c, [-F.col("level"), -F.col("size"), F.col("component")], "size").select("component", "level", "size", F.col("place").alias("ordinal"), F.col("before").alias("first"))


def reorder(p: Partition) -> DataFrame:
    """(id, position): vertices of a component stand together, components in order."""
    first = order_components(p).select("component", "first")
    v = p.vertices.join(first, "component").select("id", "first", F.lit(1).alias("one"))
    return running(v, [F.col("first"), F.col("id")], "one").select("id", F.col("place").alias("position"))


def classify_edges(p: Partition) -> DataFrame:
    """(src, dst, prob, edge_class, src_level, dst_level, src_component, dst_component)."""
    a = p.vertices.select(F.col("id").alias("src"), F.col("level").alias("src_level"), F.col("component").alias("src_component"))
    b = p.vertices.select(F.col("id").alias("dst"), F.col("level").alias("dst_level"), F.col("component").alias("dst_component"))
    kind = F.when(F.col("src") == F.col("dst"), "loop").when(F.col("src_component") == F.col("dst_component"), "inside").otherwise("between")
    return p.graph.edges.join(a, "src").join(b, "dst").select("src", "dst", "prob", kind.alias("edge_class"), "src_level", "dst_level", "src_component", "dst_component")


def solver_of(policy: Policy, kind: Column, size: Column, edges: Column, local_edges: int) -> Column:
    """Solver choice as an expression: single, acyclic, acyclic_distributed, dense, series_local or series_distributed."""
    return F.when(size == 1, "single").when(kind == "cac", F.when(edges <= local_edges, "acyclic").otherwise("acyclic_distributed" if policy.acyclic == "acyclic" else "series_distributed")).when(size < policy.dense_below, "dense").when(edges <= local_edges, "series_local").otherwise("series_distributed")


def plan_blocks(p: Partition, policy: Policy | None = None, local_edges: int = 2_000_000, bin_edges: int = 500_000) -> DataFrame:
    """(component, level, kind, size, inside_edges, solver, bin): largest first, packed by running
    sums so that a bin holds about ``bin_edges`` edges; single vertices of a level are pooled in bin -1."""
    inside = classify_edges(p).where("edge_class = 'inside'").groupBy(F.col("src_component").alias("component")).agg(F.count("*").alias("inside_edges"))
    c = component_table(p).join(inside, "component", "left").fillna(0, ["inside_edges"])
    c = c.withColumn("solver", solver_of(policy or Policy(), F.col("kind"), F.col("size"), F.col("inside_edges"), local_edges))
    multi = c.where("size > 1").withColumn("_cost", F.col("inside_edges") + F.col("size"))
    run = running(multi, [-F.col("level"), -F.col("inside_edges"), F.col("component")], "_cost")
    start = run.groupBy("level").agg(F.min("before").alias("start"))
    multi = run.join(F.broadcast(start), "level").withColumn("bin", F.floor((F.col("before") - F.col("start")) / bin_edges).cast("int")).select(*c.columns, "bin")
    return multi.unionByName(c.where("size = 1").withColumn("bin", F.lit(-1)))


def level_groups(p: Partition, min_vertices: int = 100) -> list[tuple[int, int, bool]]:
    """(level, block level, fused): runs of adjacent levels under ``min_vertices`` become one block level."""
    rows = small_rows(level_profile(p).select("level", "n_vertices").orderBy("level"), MAX_LEVELS, "levels")
    out, group, small_before = [], -1, False
    for r in rows:
        small = r.n_vertices < min_vertices
        group += not (small and small_before)
        small_before = small
        out.append((r.level, group))
    many = Counter(g for _, g in out)
    return [(k, g, many[g] > 1) for k, g in out]


def merge_small_levels(p: Partition, min_vertices: int = 100) -> DataFrame:
    """(id, block_level): runs of adjacent levels under ``min_vertices`` become one block level."""
    table = p.vertices.sparkSession.createDataFrame([(k, g) for k, g, _ in level_groups(p, min_vertices)], "level int, block_level int")
    return p.vertices.join(F.broadcast(table), "level").select("id", "block_level")


def scc_partition(p: Partition) -> Partition:
    """The same graph by strongly connected sets and their levels alone; single vertices are acyclic components."""
    size = p.vertices.groupBy("scc").agg(F.count("*").alias("size"))
    v = p.vertices.drop("size", "component", "kind", "level").join(size, "scc")
    kind = F.when(F.col("size") > 1, "scc").otherwise("cac")
    return Partition(p.graph, v.select("id", F.col("scc").alias("component"), kind.alias("kind"), "size", F.col("scc_level").alias("level"), "scc", "scc_level"))


def merged_partition(p: Partition, min_vertices: int) -> Partition:
    """Runs of small levels as one component each, which is solved as if strongly connected."""
    table = p.vertices.sparkSession.createDataFrame(level_groups(p, min_vertices), "level int, block int, fused boolean")
    v = p.vertices.join(F.broadcast(table), "level").drop("level")
    of = v.where("fused").groupBy("block").agg(F.min("id").alias("lead"), F.count("*").alias("all"))
    v = v.join(F.broadcast(of), "block", "left")
    fused = F.col("fused")
    return Partition(p.graph, v.select("id", F.when(fused, F.col("lead")).otherwise(F.col("component")).alias("component"), F.when(fused, "scc").otherwise(F.col("kind")).alias("kind"), F.when(fused, F.col("all")).otherwise(F.col("size")).alias("size"), F.col("block").alias("level"), "scc", "scc_level"))


def density_map(g: Graph, position: DataFrame, bins: int = 64) -> DataFrame:
    """(row_bin, col_bin, n): edges per cell of the adjacency picture under a vertex order (id, position)."""
    n = position.agg((F.max("position") + 1).alias("n"))
    placed = position.crossJoin(F.broadcast(n)).select("id", F.floor(F.col("position") * bins / F.col("n")).cast("int").alias("bin"))
    a, b = placed.select(F.col("id").alias("src"), F.col("bin").alias("row_bin")), placed.select(F.col("id").alias("dst"), F.col("bin").alias("col_bin"))
    return g.edges.join(a, "src").join(b, "dst").groupBy("row_bin", "col_bin").agg(F.count("*").alias("n"))
