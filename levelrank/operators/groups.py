"""Vertex groups, peeling and component descriptions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.operators.model import Graph, Partition
from levelrank.operators.partition import contract
from levelrank.plans.staging import materialise


def degrees(g: Graph) -> DataFrame:
    """(id, out_degree, in_degree) of every vertex, isolated ones with zeros."""
    ends = g.edges.select(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(g.edges.select(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    none = g.vertices.select("id", F.lit(0).alias("o"), F.lit(0).alias("i"))
    return ends.unionByName(none).groupBy("id").agg(F.sum("o").alias("out_degree"), F.sum("i").alias("in_degree"))


def vertex_groups(p: Partition) -> DataFrame:
    """(id, grp): 1 isolated, 2 only out-edges, 3 only in-edges, 4 both but on no cycle, 5 on a cycle."""
    d = degrees(p.graph).join(p.vertices.select("id", "kind"), "id")
    out, into = F.col("out_degree") > 0, F.col("in_degree") > 0
    return d.select("id", F.when(F.col("kind") == "scc", 5).when(~out & ~into, 1).when(out & ~into, 2).when(~out & into, 3).otherwise(4).alias("grp"))


def component_groups(p: Partition) -> DataFrame:
    """(scc, grp): the groups 1 to 4 with each strongly connected set taken as one vertex."""
    dag = contract(p.graph.edges, p.vertices.select("id", "scc"))
    ends = dag.select(F.col("a").alias("scc"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(dag.select(F.col("b").alias("scc"), F.lit(0), F.lit(1)).toDF("scc", "o", "i"))
    all_ = p.vertices.select("scc").distinct().select("scc", F.lit(0).alias("o"), F.lit(0).alias("i"))
    d = ends.unionByName(all_).groupBy("scc").agg(F.max("o").alias("o"), F.max("i").alias("i"))
    return d.select("scc", F.when((F.col("o") == 0) & (F.col("i") == 0), 1).when(F.col("i") == 0, 2).when(F.col("o") == 0, 3).otherwise(4).alias("grp"))


def peel_groups(g: Graph, max_rounds: int = 100_000) -> DataFrame:
    """(id, dangling, root, rec_dangling, rec_root, rest): overlapping groups by peeling.

    Dangling vertices have no out-edge and root vertices no in-edge; recursively so, once the
    others of the group are gone; rest is neither."""
    d = materialise(degrees(g), "degrees")

    def peel(edges: DataFrame, side: str) -> DataFrame:
        other = "dst" if side == "src" else "src"
        cur, n = materialise(edges.select("src", "dst"), "peel"), None
        for _ in range(max_rounds):
            held = cur.select(F.col(side).alias(other)).distinct()
            cur = materialise(cur.join(held, other, "left_semi").select("src", "dst"), "peel")
            now = cur.count()
            if now == n or now == 0:
                break
            n = now
        return cur.select(F.col(side).alias("id")).distinct().withColumn("held", F.lit(True))

    down, up = peel(g.edges, "src"), peel(g.edges, "dst")
    out = d.join(down.withColumnRenamed("held", "hd"), "id", "left").join(up.withColumnRenamed("held", "hu"), "id", "left")
    rd, rr = F.col("hd").isNull(), F.col("hu").isNull()
    return out.select("id", (F.col("out_degree") == 0).alias("dangling"), (F.col("in_degree") == 0).alias("root"), rd.alias("rec_dangling"), rr.alias("rec_root"), (~rd & ~rr).alias("rest"))


def inside_degrees(p: Partition) -> DataFrame:
    """(id, component, kind, size, level, in_in, in_out): degrees inside the own component."""
    v = p.vertices
    a, b = v.select(F.col("id").alias("src"), F.col("component").alias("ca")), v.select(F.col("id").alias("dst"), F.col("component").alias("cb"))
    inside = p.graph.edges.where("src <> dst").join(a, "src").join(b, "dst").where("ca = cb")
    ends = inside.select(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(inside.select(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    d = ends.groupBy("id").agg(F.sum("o").alias("in_out"), F.sum("i").alias("in_in"))
    return v.join(d, "id", "left").fillna(0, ["in_out", "in_in"])


def cac_roles(p: Partition) -> DataFrame:
    """(id, leaf, head) of acyclic components: a leaf has no edge into its component, a head has."""
    d = inside_degrees(p).where("kind = 'cac'")
    return d.select("id", (F.col("in_out") == 0).alias("leaf"), (F.col("in_out") > 0).alias("head"))


def component_shapes(p: Partition) -> DataFrame:
    """(component, kind, size, shape): single, pair, star_in, star_out, chain or general."""
    d = inside_degrees(p).groupBy("component", "kind", "size").agg(F.sum("in_out").alias("e"), F.max("in_in").alias("mi"), F.max("in_out").alias("mo"))
    shape = F.when(F.col("size") == 1, "single").when(F.col("size") == 2, "pair").when((F.col("e") == F.col("size") - 1) & (F.col("mi") == F.col("size") - 1), "star_in").when((F.col("e") == F.col("size") - 1) & (F.col("mo") == F.col("size") - 1), "star_out").when((F.col("e") == F.col("size") - 1) & (F.col("mi") == 1) & (F.col("mo") == 1), "chain").otherwise("general")
    return d.select("component", "kind", "size", shape.alias("shape"))
