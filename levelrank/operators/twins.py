"""Graphs over a task's limit as classes of targets with the same sources, where that is much smaller than their edges.

Two passes over the edges, which are never moved: hashes (two of 64 bits, and a count) of every vertex's sources, then the sources of one
vertex a class. A vertex that is itself among the sources of its like lacks its loop, so it is looked for with its own hash added too.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.functions.compact import Classes
from levelrank.operators.model import LOCAL_EDGES, Graph
from levelrank.operators.packed import HELD_EDGES, MOST_VERTICES

#: Members of classes must be fewer than the edges by this factor, or edges stay as they are; up to so many edges frames do not look for classes.
SMALLER, FEW_EDGES = 4, 200_000


def _hashes(x: str) -> list:
    return [F.xxhash64(F.col(x)), F.xxhash64(F.col(x), F.lit(1))]


def classes(g: Graph, local_edges: int = LOCAL_EDGES) -> tuple[np.ndarray, np.ndarray, Classes] | None:
    """(ids, weights, classes) of a graph without loops over ``local_edges`` edges; None for smaller graphs, for those with probabilities that
    differ inside a source, over ``MOST_VERTICES`` vertices, or where classes do not win."""
    if g.edges.limit(local_edges + 1).count() <= local_edges or g.vertices.limit(MOST_VERTICES + 1).count() > MOST_VERTICES:
        return None
    a, b = _hashes("src")
    into = g.edges.groupBy("dst").agg(F.bit_xor(a).alias("a"), F.bit_xor(b).alias("b"), F.count("*").alias("n"), F.count_if(F.col("src") == F.col("dst")).alias("loops")).toArrow()
    if into["loops"].to_numpy().any():
        return None
    v = g.vertices.select("id", "weight", *(h.alias(x) for h, x in zip(_hashes("id"), "ab"))).toArrow()
    order = np.argsort(v["id"].to_numpy())
    ids, weight, own_a, own_b = (v[x].to_numpy()[order] for x in ("id", "weight", "a", "b"))
    n, at = len(ids), np.searchsorted(ids, into["dst"].to_numpy())
    open_ = np.zeros((n, 3), np.int64)
    for j, x in enumerate("abn"):
        open_[at, j] = into[x].to_numpy()
    closed = np.c_[open_[:, 0] ^ own_a, open_[:, 1] ^ own_b, open_[:, 2] + 1]
    on = np.flatnonzero(open_[:, 2])
    keys, of, size = np.unique(np.r_[open_[on], closed[on]], axis=0, return_inverse=True, return_counts=True)
    plain, with_own = np.split(of.ravel(), 2)
    own = np.zeros(n, bool)
    own[on] = size[with_own] > size[plain]  # the more vertices may share a class the better; either is right
    used, cls_on = np.unique(np.where(own[on], with_own, plain), return_inverse=True)
    members = keys[used][:, 2]
    if members.sum() > min(HELD_EDGES, into["n"].to_numpy().sum() // SMALLER):
        return None
    cls = np.full(n, -1, np.int64)
    cls[on] = cls_on
    _, first = np.unique(cls_on, return_index=True)
    stands = on[first]  # a vertex of each class
    spark = g.edges.sparkSession
    shares = g.edges.groupBy("src").agg(F.min("prob").alias("lo"), F.max("prob").alias("hi")).toArrow()
    if (shares["lo"].to_numpy() != shares["hi"].to_numpy()).any():
        return None
    prob = np.zeros(n)
    prob[np.searchsorted(ids, shares["src"].to_numpy())] = shares["lo"].to_numpy()
    table = spark.createDataFrame(pd.DataFrame({"dst": ids[stands], "k": np.arange(len(stands))}))
    got = g.edges.join(F.broadcast(table), "dst").select("src", "k").toArrow()
    mine = np.flatnonzero(own[stands])
    es = np.r_[np.searchsorted(ids, got["src"].to_numpy()), stands[mine]]
    ek = np.r_[got["k"].to_numpy(), mine]
    by = np.lexsort((es, ek))
    return ids, weight.astype(float), Classes(n, len(stands), prob, cls, own, es[by], ek[by])


def in_task(spark, make: Callable[..., pd.DataFrame], schema: str, *arrays) -> DataFrame:
    """``make(*arrays)`` in one task, to which the arrays are sent."""
    shared = spark.sparkContext.broadcast(arrays)

    def run(batches):
        for b in batches:
            if len(b):
                yield make(*shared.value)

    return spark.range(0, 1, 1, 1).mapInPandas(run, schema)
