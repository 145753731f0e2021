"""Graphs and partitions as pairs of lazily planned frames."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Edges that one task's kernels take; above it the distributed routes run.
LOCAL_EDGES = 2_000_000


@dataclass(frozen=True)
class Graph:
    """vertices (id long, weight double); edges (src long, dst long, prob double), no repeats."""

    vertices: DataFrame
    edges: DataFrame


@dataclass(frozen=True)
class Partition:
    """vertices (id, component, kind, size, level, scc, scc_level) of a graph."""

    graph: Graph
    vertices: DataFrame


def edge_probabilities(edges: DataFrame, weight: str | None = None, renormalise: bool = True) -> DataFrame:
    """(src, dst, prob): 1/outdegree, or the weight's share of its source. Weights that are
    probabilities already (rows may sum to less than one) pass with ``renormalise=False``."""
    if weight and not renormalise:
        return edges.select("src", "dst", F.col(weight).cast("double").alias("prob"))
    of = F.col(weight).cast("double") if weight else F.lit(1.0)
    total = edges.groupBy("src").agg(F.sum(of).alias("total"))  # summed in tasks first; a hub's edges stay dealt out
    return edges.join(total.hint("shuffle_hash"), "src").select("src", "dst", (of / F.col("total")).alias("prob"))  # edges are not sorted


def build_graph(edges: DataFrame, vertices: DataFrame | None = None, *, src: str = "src", dst: str = "dst", edge_weight: str | None = None, vertex_weight: str | None = None, loops: str = "drop", renormalise: bool = True, keys: str = "long", repeats: bool = True) -> Graph:
    """A simple graph: rows with a null end go, repeats merge (weights add up), loops go
    unless kept. Vertices are the ends of edges, loops included, and those of the vertex
    frame (id and optionally a weight; null weights count as 0). ``keys='encode'`` numbers
    arbitrary keys by a dictionary frame, see ``encode``. ``repeats=False``: the caller has made sure that no row is repeated."""
    if keys == "encode":
        return encode(edges, src, dst)[0]
    plain = edges.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), (F.col(edge_weight).cast("double") if edge_weight else F.lit(1.0)).alias("w")).where("src is not null and dst is not null")
    if repeats:
        plain = plain.groupBy("src", "dst").agg((F.sum("w") if edge_weight else F.first("w")).alias("w"))
        ids = plain.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    else:  # no table of twice the edges
        ids = plain.select(F.col("src").alias("id")).distinct().union(plain.select(F.col("dst").alias("id")).distinct()).distinct()
    if vertices is not None:
        known = vertices.where("id is not null").groupBy(F.col("id").cast("long").alias("id")).agg(F.first(F.col(vertex_weight).cast("double") if vertex_weight else F.lit(1.0)).alias("weight"))
        known = known.withColumn("weight", F.coalesce("weight", F.lit(0.0)))
        nodes = ids.join(known, "id", "full").select("id", F.coalesce("weight", F.lit(1.0 if not vertex_weight else 0.0)).alias("weight"))
    else:
        nodes = ids.withColumn("weight", F.lit(1.0))
    kept = plain.where("src <> dst") if loops == "drop" else plain
    return Graph(nodes, edge_probabilities(kept, "w", renormalise))


def encode(edges: DataFrame, src: str = "src", dst: str = "dst") -> tuple[Graph, DataFrame]:
    """Graph over numbered keys and the dictionary (key, id). Numbers come from the partition and place
    of the distinct keys, written first, so they stay the same on recomputation."""
    from levelrank.plans.staging import materialise

    keys = edges.select(F.explode(F.array(F.col(src).cast("string"), F.col(dst).cast("string"))).alias("key")).where("key is not null").distinct()
    names = materialise(keys.withColumn("id", F.monotonically_increasing_id()), "keys")
    a, b = names.select(F.col("key").alias("ka"), F.col("id").alias("src")), names.select(F.col("key").alias("kb"), F.col("id").alias("dst"))
    plain = edges.select(F.col(src).cast("string").alias("ka"), F.col(dst).cast("string").alias("kb"))
    coded = plain.join(a, "ka").join(b, "kb").select("src", "dst")
    return build_graph(coded), names


def normalise(ranks: DataFrame) -> DataFrame:
    """Adds rank_norm: ranks scaled to sum 1."""
    total = ranks.agg(F.sum("rank").alias("total"))
    return ranks.crossJoin(F.broadcast(total)).withColumn("rank_norm", F.col("rank") / F.col("total")).drop("total")  # one row


def rescale(normalised: DataFrame, g: Graph, c: float = 0.85) -> DataFrame:
    """Normalised ranks back to start weights: scale by total weight over the mass a step loses."""
    moved = g.edges.join(normalised, g.edges.src == normalised.id).agg((c * F.sum(F.col("prob") * F.col("rank_norm"))).alias("moved"))
    total = g.vertices.agg(F.sum("weight").alias("total"))
    scale = moved.crossJoin(total).select((F.col("total") / (1 - F.coalesce("moved", F.lit(0.0)))).alias("scale"))
    return normalised.crossJoin(F.broadcast(scale)).select("id", (F.col("rank_norm") * F.col("scale")).alias("rank"), "rank_norm")
