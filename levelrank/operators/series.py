"""The power series on frames, with edges that stay where they are.

Edges are written once as a table bucketed by source, and so is the state of every round: reading them
back needs no exchange. A round is then one join in place and one exchange, that of the partly summed
gains by target, whatever the number of edges. The state is written every ``PER_JOB`` rounds; one row of scalars a job
reaches the driver.

Terms are not summed one by one to the end. Edges and weights are not negative, so if the last term lies between ``low`` and
``high`` times the term at an earlier mark, entry by entry, all that is still to come lies between low/(1-low) and
high/(1-high) times what was added since the mark. The loop ends where these two differ by no more than the tolerance,
or by ``LEAST`` times the largest rank where that is more, and adds the lower one. But for rounding, which shares of
nearly equal terms hold too, the result is not over the whole sum and off by no more than that.

Over ``FEW_EDGES`` edges, classes of targets with the same sources are looked for first (``twins``). Where they win, one task
holds their members, and sums go on there to their tolerance, round by round and group by group as on frames.
"""

from __future__ import annotations

import math
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelrank.functions import compact as C
from levelrank.functions.kernels import Unfinished
from levelrank.operators.model import Graph
from levelrank.operators.packed import MOST_VERTICES
from levelrank.operators.twins import FEW_EDGES, classes, in_task
from levelrank.plans.staging import materialise, shared_path

#: Rounds between two writes of the state. Edges of a bucket, and how many buckets there may be.
PER_JOB, BUCKET_EDGES, MAX_BUCKETS = 3, 4_000_000, 50_000
#: Share of the largest rank that sums of doubles over many rounds do not hold; a rest known to it is known.
LEAST = 4e-15
#: The mark moves to the present round when this many times the rounds up to it have gone.
MARK = 1.3


class Placed:
    """Tables bucketed by one column, all in as many buckets, so that joins on it move neither side.

    Use as a context: the catalogue forgets the tables at the end, their files stay for the shared folder's
    own clean-up, as those of ``materialise`` do."""

    def __init__(self, spark, buckets: int):
        self.spark, self.buckets, self.names = spark, buckets, []

    def __enter__(self) -> Placed:
        return self

    def __exit__(self, *_) -> None:
        for name in self.names:
            self.spark.sql(f"DROP TABLE IF EXISTS {name}")

    def write(self, df: DataFrame, key: str, what: str, folders: str | None = None) -> DataFrame:
        """The written table; with ``folders`` one folder per value of that column, so that a filter on it reads no other file."""
        name = f"lr_{what}_{uuid.uuid4().hex}"
        dealt = df.repartition(self.buckets, key).write
        dealt = dealt.partitionBy(folders) if folders else dealt
        dealt.bucketBy(self.buckets, key).option("path", shared_path(self.spark, what)).saveAsTable(name)
        self.names.append(name)
        return self.spark.table(name)


def buckets_for(edges: DataFrame, least: int = 1) -> int:
    """Buckets by the number of edges; never under the session's shuffle partitions, or the planner would move both sides."""
    n = edges.count()
    wanted = max(least, -(-n // BUCKET_EDGES), int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return min(wanted, MAX_BUCKETS)


def gains(sent: DataFrame, edges: DataFrame, c: float) -> DataFrame:
    """(id, gain): one scatter of (id, out) along edges in place, which are not sorted, summed in tasks before the one exchange."""
    moved = edges.join(sent.hint("shuffle_hash"), edges.src == sent.id).select(F.col("dst").alias("id"), (c * F.col("prob") * F.col("out")).alias("gain"))
    return moved.groupBy("id").agg(F.sum("gain").alias("gain"))


def one_round(state: DataFrame, edges: DataFrame, c: float, tol: float, freeze: bool) -> DataFrame:
    """(id, term, rank, waiting) after one more term; with ``freeze`` vertices under the tolerance wait until more has come.
    Other columns of the state stay."""
    total = F.col("waiting") + F.col("term")
    go = total > tol if freeze else F.lit(True)
    others = [x for x in state.columns if x not in ("id", "term", "rank", "waiting")]
    sent = state.select("id", F.when(go, total).otherwise(0.0).alias("out"), F.when(go, 0.0).otherwise(total).alias("waiting"), "rank", *others)
    gain = gains(sent.select("id", "out"), edges, c)
    term = F.coalesce("gain", F.lit(0.0))
    return sent.join(gain.hint("shuffle_hash"), "id", "left").select("id", term.alias("term"), (F.col("rank") + term).alias("rank"), "waiting", *others)


def marked(state: DataFrame) -> DataFrame:
    """The state with its term and rank as those of the mark."""
    return state.withColumns({"term0": F.col("term"), "rank0": F.col("rank")})


def progress(state: DataFrame, held: Column | None = None):
    """One row: the largest entry of the last term (with what ``held`` keeps back), its shares of the marked term, the most
    that came since the mark, and the largest rank."""
    share = F.when(F.col("term0") > 0, F.col("term") / F.col("term0")).when(F.col("term") > 0, F.lit(math.inf))
    top = F.max(F.col("term") + (F.lit(0.0) if held is None else held))
    return state.agg(top.alias("top"), F.min(share).alias("low"), F.max(share).alias("high"), F.max(F.col("rank") - F.col("rank0")).alias("since"), F.max("rank").alias("most")).first()


def closing(at, tol: float) -> float | None:
    """The factor of what came since the mark that is surely still to come, if all that may come differs by no more than ``tol``."""
    if at.low is None or not at.high < 1:
        return None
    low, high = at.low / (1 - at.low), at.high / (1 - at.high)
    return low if at.since * (high - low) <= max(tol, LEAST * at.most) else None


def closed(state: DataFrame, factor: float) -> DataFrame:
    return state.select("id", (F.col("rank") + factor * (F.col("rank") - F.col("rank0"))).alias("rank"))


def not_negative(vertices: DataFrame, edges: DataFrame) -> bool:
    return (edges.agg(F.min("prob")).first()[0] or 0.0) >= 0 and (vertices.agg(F.min("weight")).first()[0] or 0.0) >= 0


def over_classes(vertices: DataFrame, edges: DataFrame, solve) -> tuple[DataFrame, int] | None:
    """(ranks, rounds) that ``solve(ids, weights, classes) -> rank, rounds`` gives in one task; None where edges stay as they are."""
    if edges.limit(FEW_EDGES + 1).count() <= FEW_EDGES:
        return None
    got = classes(Graph(vertices.select("id", "weight"), materialise(edges.select("src", "dst", "prob"), "edges")), FEW_EDGES)
    if got is None:
        return None

    def make(ids, weight, g) -> pd.DataFrame:
        rank, rounds = solve(ids, weight, g)
        return pd.DataFrame({"id": ids, "rank": rank, "rounds": rounds})

    ranks = materialise(in_task(vertices.sparkSession, make, "id long, rank double, rounds int", *got), "ranks")
    return ranks.select("id", "rank"), ranks.first()["rounds"]


def series_distributed(vertices: DataFrame, edges: DataFrame, c: float, tol: float, max_rounds: int | None = None, freeze: bool = False, per_job: int = PER_JOB) -> tuple[DataFrame, int]:
    """(ranks, rounds) of the power series over (id, weight) and (src, dst, prob).

    Stops when no entry of the last term is over ``tol``, or (not with ``freeze``) when the rest is known to ``tol``, which is
    added. Raises ``Unfinished`` where ``max_rounds`` (by default what a damped graph can need) comes first."""
    bound = max_rounds or round_bound(c, tol)
    spark = vertices.sparkSession
    if not freeze and max_rounds is None:
        got = over_classes(vertices, edges, lambda ids, w, g: C.series_stops(g, w, c, (tol,))[0][:2])
        if got is not None:
            return got
    with Placed(spark, buckets_for(edges)) as place:
        fixed = place.write(edges.select("src", "dst", "prob"), "src", "edges")
        start = vertices.select("id", F.col("weight").alias("term"), F.col("weight").alias("rank"), F.lit(0.0).alias("waiting"))
        state = place.write(marked(start), "id", "state")
        rounds, mark, may_close = 0, 0, not freeze and not_negative(vertices, fixed)
        at = progress(state)
        while (at.top or 0.0) > tol:
            factor = closing(at, tol) if may_close else None
            if factor is not None:
                return materialise(closed(state, factor), "ranks"), rounds
            if rounds >= bound:
                raise Unfinished(f"the series is not at {tol} after {rounds} rounds")
            if rounds >= MARK * mark:
                state, mark = marked(state), rounds
            for _ in range(min(per_job, bound - rounds)):
                state = one_round(state, fixed, c, tol, freeze)
                rounds += 1
            state = place.write(state, "id", "state")
            at = progress(state, F.col("waiting"))
        return materialise(state.select("id", "rank"), "ranks"), rounds


def round_bound(c: float, tol: float, start: float = 1e12) -> int:
    """Rounds after which no term of a graph with start weights up to ``start`` in all can be over the tolerance; for c = 1, where
    nothing damps, a million."""
    return 1_000_000 if c >= 1 else max(100, math.ceil(math.log(max(tol, 1e-300) / start) / math.log(c)) + 10)


def acyclic_distributed(vertices: DataFrame, edges: DataFrame, c: float, max_rounds: int = 1_000_000) -> tuple[DataFrame, int]:
    """(ranks, waves) of a graph without cycles but for loops, (id, weight, loop) and (src, dst, prob): a wave of
    vertices whose in-edges are all done hands its final ranks on, so every edge is used once, whatever the tolerance.

    Edges lie in place by source; a wave sends only what its own vertices hand on, and the state of the others
    takes the sums and the number of in-edges that came."""
    spark = vertices.sparkSession
    with Placed(spark, buckets_for(edges)) as place:
        fixed = place.write(edges.select("src", "dst", "prob"), "src", "edges")
        left = fixed.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("open"))
        state = vertices.select("id", F.col("weight").alias("w"), "loop").join(left, "id", "left").select("id", "w", "loop", F.coalesce("open", F.lit(0)).alias("open"))
        state = place.write(state, "id", "state")
        total, done, out = state.count(), 0, None
        for waves in range(1, max_rounds + 1):
            wave = materialise(state.where("open = 0").select("id", (F.col("w") / (1 - c * F.col("loop"))).alias("rank")), "wave")
            n = wave.count()
            out = wave if out is None else out.unionByName(wave)
            done += n
            if done == total:
                return out, waves
            if not n:
                raise ValueError("the graph has a cycle")
            came = fixed.join(wave, fixed.src == wave.id).groupBy(F.col("dst").alias("id")).agg(F.sum(c * F.col("prob") * F.col("rank")).alias("gain"), F.count("*").alias("came"))
            rest = state.where("open > 0").join(came, "id", "left")
            state = place.write(rest.select("id", (F.col("w") + F.coalesce("gain", F.lit(0.0))).alias("w"), "loop", (F.col("open") - F.coalesce("came", F.lit(0))).alias("open")), "id", "state")
        raise Unfinished("waves did not end")


def gauss_seidel_distributed(vertices: DataFrame, edges: DataFrame, c: float, tol: float, parts: int = 8, max_rounds: int | None = None) -> tuple[DataFrame, int]:
    """(ranks, sweeps) of x = W + Mx where ``parts`` groups of vertices take turns: a group's new values count for the groups
    after it in the same sweep. With one group this is the Jacobi form, with one per vertex the sequential sweep.

    What goes round is the change of each vertex in its last turn, from x = 0: a group's changes are the scatter of the newest
    changes of all. They are the terms of a sum and its rest is closed as that of the series."""
    bound = max_rounds or round_bound(c, tol)
    group = lambda x: F.pmod(F.xxhash64(x), F.lit(parts)).cast("int")
    of = vertices.select("id", group("id").alias("part"))
    if edges.limit(FEW_EDGES + 1).count() > FEW_EDGES and vertices.limit(MOST_VERTICES + 1).count() <= MOST_VERTICES:
        known = of.toArrow()
        order = np.argsort(known["id"].to_numpy())
        turn = vertices.sparkSession.sparkContext.broadcast(known["part"].to_numpy()[order])
        got = over_classes(vertices, edges, lambda ids, w, g: C.in_turns(g, w, c, tol, turn.value, bound))
        if got is not None:
            return got
    with Placed(vertices.sparkSession, buckets_for(edges)) as place:
        fixed = place.write(edges.select("src", "dst", "prob", group("dst").alias("to")), "src", "edges", "to")
        zero = F.lit(0.0)
        state = place.write(marked(vertices.select("id", "weight", group("id").alias("part"), zero.alias("term"), zero.alias("rank"))), "id", "state")
        mark, may_close = 0, not_negative(vertices, fixed)
        for sweep in range(1, bound + 1):
            if sweep - 1 >= MARK * mark:
                state, mark = marked(state), sweep - 1
            for k in range(parts):
                gain = gains(state.select("id", F.col("term").alias("out")), fixed.where(F.col("to") == k), c)
                own, new = F.col("part") == k, F.coalesce("gain", zero) + (F.col("weight") if sweep == 1 else zero)
                state = state.join(gain.hint("shuffle_hash"), "id", "left").select("id", "weight", "part", F.when(own, new).otherwise(F.col("term")).alias("term"), (F.col("rank") + F.when(own, new).otherwise(0.0)).alias("rank"), "term0", "rank0")
                if k % PER_JOB == PER_JOB - 1 or k == parts - 1:
                    state = place.write(state, "id", "state")
            at = progress(state, None if may_close else F.abs("term") - F.col("term"))
            if (at.top or 0.0) <= tol:
                return materialise(state.select("id", "rank"), "ranks"), sweep
            factor = closing(at, tol) if may_close else None
            if factor is not None:
                return materialise(closed(state, factor), "ranks"), sweep
    raise Unfinished(f"sweeps are not at {tol} after {bound}")
