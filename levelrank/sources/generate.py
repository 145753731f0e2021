"""Generated graphs: preferential attachment, keep rules, copies and bridges.

All randomness is integer arithmetic below 2**63, so other engines can repeat it. The
endpoint list is never built: a half-edge that copies an earlier one follows that pointer
by arithmetic until it names a vertex.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from levelrank.operators.model import Graph
from levelrank.plans.staging import materialise

#: Modulus and multipliers of the hash, salts, seed graph, links per vertex.
P, A, B = 2147483647, 48271, 16807
SEED_SALT, LINK_SALT, KEEP_SALT, COUNT_SALT = 5, 11, 77, 99
SEED_VERTICES, SEED_EDGES, LINKS = 20, 50, 12
COPY_STRIDE = 10_000_000_000
CHASE = 64


def mixed(x: str, salt: int) -> str:
    """SQL text of the hash of an integer expression; the same text runs in both engines."""
    a = f"((({x}) % {P}) * {A} + {salt}) % {P}"
    return f"(((({a}) * ({a})) % {P}) * {B} + ({a})) % {P}"


def hashed(x: int, salt: int) -> int:
    a = ((x % P) * A + salt) % P
    return ((a * a % P) * B + a) % P


def seed_pairs() -> list[tuple[int, int]]:
    pairs = [(a, b) for a in range(SEED_VERTICES) for b in range(a + 1, SEED_VERTICES)]
    return sorted(sorted(pairs), key=lambda p: hashed(SEED_VERTICES * p[0] + p[1], SEED_SALT))[:SEED_EDGES]


def _first_of(edge: str) -> str:
    """Half-edges that exist before the vertex of an edge joins."""
    return f"(2 * ({SEED_EDGES} + {LINKS} * ((({edge}) - {SEED_EDGES}) div {LINKS})))"


def preferential_graph(spark: SparkSession, n: int | DataFrame) -> DataFrame:
    """(a, b): undirected distinct edges over 0..n-1, or over the frame (id) of those numbers."""
    seeds = seed_pairs()
    ends = [v for p in seeds for v in p]
    table = F.array(*[F.lit(v).cast("long") for v in ends])
    ids = spark.range(n) if isinstance(n, int) else n
    first = F.lit(SEED_EDGES) + (F.col("id") - SEED_VERTICES) * LINKS
    e = ids.where(F.col("id") >= SEED_VERTICES).select(F.explode(F.sequence(first, first + (LINKS - 1))).alias("e"))
    start = f"({mixed('e', LINK_SALT)}) % {_first_of('e')}"
    follow = f"({mixed('t div 2', LINK_SALT)}) % {_first_of('t div 2')}"
    t = F.expr(f"aggregate(sequence(1, {CHASE}), {start}, (t, k) -> CASE WHEN t >= {2 * SEED_EDGES} AND t % 2 = 1 THEN {follow} ELSE t END)")
    joined = e.withColumn("t", t).select((F.lit(SEED_VERTICES) + F.expr(f"(e - {SEED_EDGES}) div {LINKS}")).alias("a"), F.when(F.col("t") < 2 * SEED_EDGES, F.element_at(table, (F.least("t", F.lit(2 * SEED_EDGES - 1)) + 1).cast("int"))).otherwise(F.lit(SEED_VERTICES) + F.expr(f"(t div 2 - {SEED_EDGES}) div {LINKS}")).alias("b"))
    both = joined.unionByName(spark.createDataFrame(seeds, "a long, b long"))
    return both.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _keep(und: DataFrame, kept: str) -> DataFrame:
    """Directed edges to the neighbours of smallest hash. Degrees are counted in tasks first, and a hub's neighbours over
    the first of its share never meet: only what may be kept is sorted by vertex."""
    near = und.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(und.select(F.col("b").alias("src"), F.col("a").alias("dst")))
    degree = near.groupBy("src").agg(F.count("*").alias("d"))
    ranked = near.join(degree, "src").withColumn("h", F.expr(mixed("src * 1000003 + dst", KEEP_SALT)))
    w = Window.partitionBy("src", F.pmod("dst", F.lit(64))).orderBy("h", "dst")
    some = ranked.withColumn("r", F.row_number().over(w)).where(F.expr(f"r <= {kept}"))  # the first of each of 64 shares hold the first of all
    return some.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy("h", "dst"))).where(F.expr(f"r <= {kept}")).select("src", "dst")


def keep_log_edges(und: DataFrame) -> DataFrame:
    """Directed: each vertex keeps ceil(log2 degree) of its edges, those of smallest hash."""
    return _keep(und, "(CASE WHEN d <= 1 THEN 0 ELSE length(bin(d - 1)) END)")


def keep_few_edges(und: DataFrame) -> DataFrame:
    """Directed: each vertex keeps none, one or two."""
    return _keep(und, f"({mixed('src', COUNT_SALT)}) % 3")


def generated(spark: SparkSession, n: int | DataFrame, dense: bool) -> tuple[DataFrame, DataFrame]:
    """(vertices (id), edges (src, dst)), isolated vertices included."""
    und = preferential_graph(spark, n)
    return spark.range(n) if isinstance(n, int) else n, (keep_log_edges if dense else keep_few_edges)(und)


def replicate(edges: DataFrame, copies: int = 10) -> DataFrame:
    """Disjoint copies: ids of copy k are moved by k strides."""
    k = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(copies - 1).cast("long")))
    return edges.select("src", "dst", k.alias("k")).select((F.col("src") + F.col("k") * COPY_STRIDE).alias("src"), (F.col("dst") + F.col("k") * COPY_STRIDE).alias("dst"))


def bridge(copies: DataFrame, one: DataFrame, extra: int = 20, range_ids: int = 100_000) -> DataFrame:
    """Adds ``extra`` edges between copies; ends are picked by place in the sorted vertex list of one copy."""
    ids = one.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    n = ids.count()
    wanted = [((i * 7919) % n, (i * 104729 + 1) % n, i % 10, (i * 3 + 1) % 10) for i in range(extra)] if n else []
    spark = one.sparkSession
    places = sorted({p for w in wanted for p in w[:2]})
    parts = max(1, min(200, n // range_ids + 1))
    # written once: the bounds of ranges are sampled, so each computation would cut them elsewhere
    ranked = materialise(ids.repartitionByRange(parts, "id").select("id", F.spark_partition_id().alias("p")), "ranked")
    sizes = {r.p: r["count"] for r in ranked.groupBy("p").count().collect()}
    before = {p: sum(c for q, c in sizes.items() if q < p) for p in sizes}
    table = spark.createDataFrame(list(before.items()) or [(0, 0)], "p int, before long")
    at = ranked.join(F.broadcast(table), "p").withColumn("place", F.col("before") + F.row_number().over(Window.partitionBy("p").orderBy("id")) - 1)
    got = {r.place: r.id for r in at.where(F.col("place").isin(places)).collect()} if places else {}
    rows = [(got[a] + x * COPY_STRIDE, got[b] + y * COPY_STRIDE) for a, b, x, y in wanted]
    return copies.unionByName(spark.createDataFrame(rows, "src long, dst long")) if rows else copies


def copied(g: Graph, copies: int = 10, bridged: bool = False) -> Graph:
    """``copies`` of a graph of equal shares as frames over it, nothing written or moved: ids and edges are shifted, shares stay but
    for the sources of bridges."""
    k = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(copies - 1).cast("long")))
    move = lambda x: F.col(x) + F.col("k") * COPY_STRIDE
    vertices = g.vertices.select("id", "weight", k.alias("k")).select(move("id").alias("id"), "weight")
    edges = g.edges.select("src", "dst", "prob", k.alias("k")).select(move("src").alias("src"), move("dst").alias("dst"), "prob")
    if bridged:
        ends = g.vertices.select(F.col("id").alias("src"), F.col("id").alias("dst"))
        new = sorted({tuple(r) for r in bridge(ends.limit(0), ends).collect()})  # 20 rows
        own = {s: s % COPY_STRIDE for s, _ in new}
        degree = {r.src: r.n for r in g.edges.where(F.col("src").isin(sorted(set(own.values())))).groupBy("src").agg(F.count("*").alias("n")).collect()}
        total = {s: degree.get(at, 0) + sum(s == x for x, _ in new) for s, at in own.items()}
        if new:
            shares = g.edges.sparkSession.createDataFrame([(s, 1 / n) for s, n in total.items()], "src long, share double")
            edges = edges.join(F.broadcast(shares), "src", "left").select("src", "dst", F.coalesce("share", "prob").alias("prob"))
            edges = edges.unionByName(g.edges.sparkSession.createDataFrame([(s, t, 1 / total[s]) for s, t in new], "src long, dst long, prob double"))
    return Graph(vertices, edges)


def register_copies(spark: SparkSession) -> None:
    """The table function ``edge_copies(src, dst, copies)``: an edge once per copy, for LATERAL joins in SQL."""
    from pyspark.sql.functions import udtf

    class EdgeCopies:
        def eval(self, src: int, dst: int, copies: int):
            for k in range(copies):
                yield src + k * COPY_STRIDE, dst + k * COPY_STRIDE

    spark.udtf.register("edge_copies", udtf(EdgeCopies, returnType="src_copy: long, dst_copy: long"))


# ---------------------------------------------------------------- as a data source
class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__((lo, hi))


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.parts = int(options.get("vertices", 1000)), int(options.get("partitions", 8))

    def partitions(self):
        last = SEED_EDGES + max(0, self.n - SEED_VERTICES) * LINKS
        cuts = [last * k // self.parts for k in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts, cuts[1:]) if a < b]

    def read(self, partition):
        seeds = seed_pairs()
        for e in range(*partition.value):
            if e < SEED_EDGES:
                yield seeds[e]
                continue
            t = hashed(e, LINK_SALT) % (2 * (SEED_EDGES + LINKS * ((e - SEED_EDGES) // LINKS)))
            while t >= 2 * SEED_EDGES and t % 2:
                h = t // 2
                t = hashed(h, LINK_SALT) % (2 * (SEED_EDGES + LINKS * ((h - SEED_EDGES) // LINKS)))
            yield SEED_VERTICES + (e - SEED_EDGES) // LINKS, seeds[t // 2][t % 2] if t < 2 * SEED_EDGES else SEED_VERTICES + (t // 2 - SEED_EDGES) // LINKS


class PreferentialAttachment(DataSource):
    """``spark.read.format("preferential_attachment").option("vertices", n)``: half-edges in the order they join."""

    @classmethod
    def name(cls):
        return "preferential_attachment"

    def schema(self):
        return "a long, b long"

    def reader(self, schema):
        return _Reader(self.options)
