"""Edge tables of the workload graphs over the given tables, and readers and writers of graph files."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Vectors that are sent to all rows at a time, and rows that meet them in one product.
KNN_BLOCK, KNN_ROWS = 20_000, 500

#: SQL that both engines run unchanged.
COMMON = {
    "basket_flow": "SELECT DISTINCT src, dst FROM (SELECT l_partkey AS src, LEAD(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_quantity) AS dst, l_quantity AS q FROM lineitem) t WHERE dst IS NOT NULL AND q <= 4",
    "trade_loop": "SELECT DISTINCT l_suppkey AS src, 1000000000 + o_custkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag <> 'R' AND l_discount = 0.0 UNION SELECT DISTINCT 1000000000 + o_custkey, l_suppkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity <= 4",
    "fk_forest": "SELECT 3000000000 + o_orderkey AS src, 2000000000 + o_custkey AS dst FROM orders UNION SELECT 2000000000 + c_custkey, CAST(1000 + c_nationkey AS BIGINT) FROM customer UNION SELECT 1000000000 + s_suppkey, CAST(1000 + s_nationkey AS BIGINT) FROM supplier UNION SELECT CAST(1000 + n_nationkey AS BIGINT), CAST(n_regionkey AS BIGINT) FROM nation",
    "square_map": "SELECT p_partkey AS src, (p_partkey * p_partkey + 1) % (SELECT COUNT(*) FROM part) AS dst FROM part",
    "affine_map": "SELECT p_partkey AS src, (p_partkey * 7 + p_size) % (SELECT COUNT(*) FROM part) AS dst FROM part",
    "turn_chain": "SELECT a.conv_id * 1000 + a.turn AS src, b.conv_id * 1000 + b.turn AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "doc_copy": "SELECT doc_id AS src, nxt AS dst FROM (SELECT doc_id, LEAD(doc_id) OVER (PARTITION BY text ORDER BY doc_id) AS nxt FROM documents) t WHERE nxt IS NOT NULL",
}
#: SQL of the other graphs, as the oracle engine runs it.
ORACLE = COMMON | {
    "event_handoff": "SELECT DISTINCT user_id AS src, nxt AS dst FROM (SELECT user_id, LEAD(user_id) OVER (ORDER BY ts, event_id) AS nxt, event_type FROM events) t WHERE nxt IS NOT NULL AND event_type = 'error' AND user_id <> nxt",
    "web_anchor": "SELECT DISTINCT l.page_id AS src, t.page_id AS dst FROM (SELECT page_id, lower(unnest(regexp_extract_all(html, 'href=\"/([^\"]*)\"', 1))) AS word FROM pages) l JOIN (SELECT page_id, lower(regexp_extract(html, '<title>([^ <]*)', 1)) AS word FROM pages) t ON l.word = t.word",
    "page_paths": "SELECT DISTINCT page_id AS src, 1000000000 + dense_rank() OVER (ORDER BY path) AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"/([^\"]*)\"', 1)) AS path FROM pages) t",
    **{f"knn{k}": f"SELECT src, dst FROM (SELECT x.vec_id AS src, y.vec_id AS dst, row_number() OVER (PARTITION BY x.vec_id ORDER BY list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) DESC, y.vec_id) AS r FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) t WHERE r <= {k}" for k in (1, 2)},
}
GRAPHS = tuple(ORACLE)
#: Graphs whose rows ``edges`` gives without repeats.
NO_REPEATS = ("web_anchor",)
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edges(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    """(src, dst) of a workload graph; repeats and loops are still in."""
    if graph in COMMON:
        sql = COMMON[graph]
        for t in TABLES:
            if f" {t}" in sql:
                table(spark, sf_dir, t).createOrReplaceTempView(t)
        return spark.sql(sql).select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
    return {"event_handoff": _handoff, "web_anchor": _anchors, "page_paths": _paths, "knn1": lambda s, d: nearest(table(s, d, "embeddings"), 1), "knn2": lambda s, d: nearest(table(s, d, "embeddings"), 2)}[graph](spark, sf_dir)


def _handoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive users: leads within a day, and from a day's last event to the next day's first."""
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type", F.to_date("ts").alias("day"))
    inner = e.withColumn("nxt", F.lead("user_id").over(Window.partitionBy("day").orderBy("ts", "event_id")))
    first = e.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("head"))
    after = first.select("day", F.lead("head").over(Window.orderBy("day")).alias("head"))  # a row per day
    both = inner.join(F.broadcast(after), "day").select("user_id", F.coalesce("nxt", "head").alias("nxt"), "event_type")
    return both.where("nxt IS NOT NULL AND event_type = 'error' AND user_id <> nxt").select(F.col("user_id").alias("src"), F.col("nxt").alias("dst")).distinct()


def _links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), F.lit(1))).alias("path"))


#: Titles whose lists by word are sent to all tasks; rows of links by title that a partition is to make.
SENT_TITLES, MADE_ROWS = 4_000_000, 2_000_000


def _anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links and titles are met as distinct (page, word): links are dealt by page and meet lists of titles, so what they make is not
    moved, and later sums by source find it where it is. Pairs can repeat only where a page has two titles."""
    from levelrank.plans.staging import materialise

    titles = table(spark, sf_dir, "pages").select(F.col("page_id").alias("dst"), F.lower(F.regexp_extract("html", "<title>([^ <]*)", 1)).alias("word"))
    titles = materialise(titles.where("word is not null").distinct(), "titles")
    links = materialise(_links(spark, sf_dir).select(F.col("page_id").alias("src"), F.lower("path").alias("word")).distinct(), "links")
    if titles.count() > SENT_TITLES:
        return links.join(titles, "word").select("src", "dst").distinct()
    lists = F.broadcast(titles.groupBy("word").agg(F.collect_list(F.struct("dst")).alias("to")))
    made = links.join(lists, "word").agg(F.sum(F.size("to"))).first()[0] or 0
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-made // MADE_ROWS))
    pairs = links.repartition(parts, "src").join(lists, "word").select("src", F.explode("to").alias("to")).select("src", F.col("to.dst").alias("dst"))
    return pairs if titles.groupBy("dst").count().where("count > 1").isEmpty() else pairs.distinct()


def _paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths numbered by rank among the distinct ones, which are counted in range partitions."""
    from levelrank.plans.blocks import running

    links = _links(spark, sf_dir).distinct()
    paths = links.select("path", F.lit(1).alias("one")).distinct()
    ids = running(paths, [F.col("path")], "one").select("path", (F.col("place") + 1).alias("r"))
    return links.join(ids, "path").select(F.col("page_id").alias("src"), (F.lit(1_000_000_000) + F.col("r")).cast("long").alias("dst"))


def nearest(vectors: DataFrame, k: int) -> DataFrame:
    """k nearest neighbours by cosine: the vectors meet all rows in blocks of ``KNN_BLOCK``."""
    v = vectors.where("vec_id is not null and embedding is not null").select("vec_id", "embedding")
    n, out = v.count(), None
    blocks = -(-n // KNN_BLOCK) or 1
    for b in range(blocks):
        part = v if blocks == 1 else v.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b)
        rows = part.orderBy("vec_id").collect()
        ids = np.array([r.vec_id for r in rows], np.int64)
        m = np.array([r.embedding for r in rows], float).reshape(len(rows), -1)
        shared = v.sparkSession.sparkContext.broadcast((ids, m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)))

        def run(batches, shared=shared):
            ids, unit = shared.value
            for x in batches:
                if not len(x) or not len(ids):
                    continue
                for lo in range(0, len(x), KNN_ROWS):
                    some = x.iloc[lo : lo + KNN_ROWS]
                    q = np.stack(some["embedding"].to_numpy()).astype(float)
                    q /= np.maximum(np.linalg.norm(q, axis=1, keepdims=True), 1e-300)
                    sim, own = q @ unit.T, some["vec_id"].to_numpy()
                    sim[own[:, None] == ids[None, :]] = -np.inf
                    least = -np.partition(-sim, min(k, sim.shape[1]) - 1, axis=1)[:, min(k, sim.shape[1]) - 1]
                    row, col = np.nonzero((sim >= least[:, None]) & np.isfinite(sim))  # ties at the last place included
                    yield pd.DataFrame({"src": own[row], "dst": ids[col], "sim": sim[row, col]})

        part_out = v.mapInPandas(run, "src long, dst long, sim double")
        out = part_out if out is None else out.unionByName(part_out)
    best = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("sim"), "dst"))
    return out.withColumn("r", best).where(F.col("r") <= k).select("src", "dst")


# ---------------------------------------------------------------- files
def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", comment: str = "#") -> DataFrame:
    """(src, dst) from delimited text with comment lines, as public graph files come."""
    return spark.read.schema("src long, dst long").option("sep", sep).option("comment", comment).csv(path)


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) from JSON lines {"id": .., "out": [..]}."""
    return spark.read.schema("id long, out array<long>").json(path).select(F.col("id").alias("src"), F.explode("out").alias("dst"))


def adjacency(edges: DataFrame) -> DataFrame:
    """(src, out array<struct<dst, prob>>): rows of the matrix."""
    return edges.groupBy("src").agg(F.sort_array(F.collect_list(F.struct("dst", "prob"))).alias("out"))


def write_partition(vertices: DataFrame, path: str) -> None:
    """Labels, one folder per level, so a level reads only its own files."""
    vertices.write.mode("overwrite").partitionBy("level").parquet(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int) -> None:
    """Edges as a table bucketed by source: joins on the source need no exchange."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)


# ---------------------------------------------------------------- joins that Spark has no name for
def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """``left`` with the ``value`` of the latest row of ``right`` of the same key at or before its ``at``: one shuffle of
    both tables together, no pair of rows is made."""
    rows = left.withColumns({"_v": F.lit(None).cast(right.schema[value].dataType), "_left": F.lit(True)})
    marks = right.select(*[F.col(c) if c in (key, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(value).alias("_v"), F.lit(False).alias("_left"))
    latest = F.last("_v", ignorenulls=True).over(Window.partitionBy(key).orderBy(at).rangeBetween(Window.unboundedPreceding, Window.currentRow))
    return rows.unionByName(marks).withColumn(f"last_{value}", latest).where("_left").drop("_v", "_left")


def interval_join(left: DataFrame, right: DataFrame, key: str, at: str, seconds: int) -> DataFrame:
    """Pairs of rows of one key where ``right`` follows ``left`` within ``seconds``: both are cut in time bins of that
    width, a row of ``left`` meets its own bin and the next one only. Columns of ``right`` come as ``next_...``."""
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    second = micros(at) / 1e6
    bin_ = F.floor(second / seconds)
    a = left.withColumn("_bin", F.explode(F.array(bin_, bin_ + 1)))
    b = right.select(F.col(key), bin_.alias("_bin"), *[F.col(c).alias(f"next_{c}") for c in right.columns if c != key])
    gap = (micros(f"next_{at}") - micros(at)) / 1e6
    return a.join(b, [key, "_bin"]).where((gap > 0) & (gap <= seconds)).drop("_bin")


def band_join(rows: DataFrame, bands: DataFrame, value: str) -> DataFrame:
    """``rows`` with the band (lo, hi, name) that holds ``value``, both ends included; bands are few and sent to all tasks."""
    return rows.join(F.broadcast(bands), F.col(value).between(F.col("lo"), F.col("hi"))).drop("lo", "hi")


def register_views(spark: SparkSession, edges: DataFrame, vertices: DataFrame, partition: DataFrame, ranks: DataFrame) -> None:
    """The views lr_edges, lr_vertices, lr_partition and lr_ranks, for SQL."""
    for name, df in (("edges", edges), ("vertices", vertices), ("partition", partition), ("ranks", ranks)):
        df.createOrReplaceTempView(f"lr_{name}")
