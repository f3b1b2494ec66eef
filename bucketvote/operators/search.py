"""Index and search: buckets, sketch cells, probes, and the tree, linear, one-level and exact strategies."""

from __future__ import annotations

from math import ceil, log2

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import key_lists, keys_of, token_number
from ..functions.similarity import cosine_sets, jaccard
from . import pairs, sketch

#: Query keys up to this many are broadcast to all nodes; beyond, the join shuffles.
BROADCAST_KEYS = 500_000


def assign_nodes(df: DataFrame, nodes: int) -> DataFrame:
    return df.withColumn("node", (token_number(F.col("id")) % nodes).cast("int"))


def build_bucket_index(sets: DataFrame, k: int, tables: int, nodes: int = 1, seed: int = 1, **options) -> DataFrame:
    """(node, table_id, bucket_key, id): narrow, no shuffle."""
    return assign_nodes(keys_of(sets, k, tables, seed, **options), nodes).select("node", "table_id", "bucket_key", "id")


def build_sketch_index(buckets: DataFrame, depth: int = sketch.DEPTH, width: int = sketch.WIDTH) -> DataFrame:
    return sketch.build_cells(buckets, ["node", "table_id", "bucket_key"], depth, width)


def build_hybrid_index(buckets: DataFrame, threshold: int = 4, depth: int = sketch.DEPTH, width: int = sketch.WIDTH) -> tuple[DataFrame, DataFrame]:
    """(raw ids of light buckets, cells of heavy ones): most buckets are nearly empty."""
    keys = ["node", "table_id", "bucket_key"]
    # a light bucket gives at most threshold ids, a heavy one only its key: neither side of a join holds a hot key's ids
    sizes = buckets.groupBy(*keys).agg(F.count("*").alias("n"))
    first = buckets.withColumn("_r", F.row_number().over(Window.partitionBy(*keys).orderBy("id"))).where(F.col("_r") <= threshold).drop("_r")
    light = first.join(sizes.where(F.col("n") <= threshold).drop("n"), keys, "left_semi")
    cells = build_sketch_index(buckets, depth, width)
    return light, cells.join(sizes.where(F.col("n") > threshold).drop("n"), keys, "left_semi")


def build_reservoir_index(buckets: DataFrame, cap: int) -> DataFrame:
    """At most cap ids a bucket: those of least salted hash, which is a uniform sample; the limit runs before the shuffle too."""
    order = Window.partitionBy("node", "table_id", "bucket_key").orderBy(sketch.salt(F.col("id"), F.col("table_id")), "id")
    return buckets.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= cap).drop("_r")


def append_index(cells: DataFrame, more: DataFrame) -> DataFrame:
    return sketch.merge_cells(cells.unionByName(more), ["node", "table_id", "bucket_key"])


def hash_queries(queries: DataFrame, k: int, tables: int, seed: int = 1, **options) -> DataFrame:
    return keys_of(queries, k, tables, seed, **options).withColumnRenamed("id", "query_id")


def probe(keys: DataFrame, index: DataFrame, queries: int | None = None, tables: int = 1) -> DataFrame:
    """index rows that the queries' keys reach. Keys are counted, unless the caller has, and broadcast if they are few; else Spark chooses."""
    if queries is None and not keys.isStreaming:
        queries, tables = keys.limit(BROADCAST_KEYS + 1).count(), 1
    small = queries is not None and queries * tables <= BROADCAST_KEYS
    return index.join(F.broadcast(keys) if small else keys, ["table_id", "bucket_key"])


def local_merge(keys: DataFrame, cells: DataFrame, **size) -> DataFrame:
    """(query_id, node, row, col, total, cand, votes): each node merges the tables a query reaches."""
    return sketch.merge_cells(probe(keys, cells, **size), ["query_id", "node"])


def tree_rounds(nodes: int) -> int:
    return ceil(log2(nodes)) if nodes > 1 else 0


def global_merge(local: DataFrame, nodes: int, strategy: str = "tree", fan_in: int = 2) -> DataFrame:
    """(query_id, row, col, total, cand, votes) over all nodes: in rounds (tree), in rounds after one gather (array), one after another (linear), or at once (multiway)."""
    if strategy == "array":
        return sketch.array_cells(local, ["query_id"], tree_rounds(nodes))
    if strategy == "linear":
        return sketch.fold_cells(local, ["query_id"])
    if strategy == "multiway":
        return sketch.merge_cells(local, ["query_id"])
    if strategy != "tree":
        raise ValueError(strategy)
    return sketch.tree_cells(local, ["query_id"], nodes, fan_in)


def on_every_node(merged: DataFrame, nodes: int) -> DataFrame:
    """The merged cells as every node would hold them after an exchange of results: a copy a node, dealt by node. Costs nodes times the cells; only where all nodes go on with the answer."""
    copies = F.explode(F.sequence(F.lit(0), F.lit(nodes - 1)))
    return merged.withColumn("node", copies).repartition(nodes, "node")


def exact_counts(keys: DataFrame, buckets: DataFrame, **size) -> DataFrame:
    """(query_id, id, hits): how many of the tables hold the candidate."""
    return probe(keys, buckets, **size).groupBy("query_id", "id").agg(F.count("*").alias("hits"))


def top_hits(counts: DataFrame, k: int, exclude_self: bool = True) -> DataFrame:
    rows = counts.where("query_id <> id") if exclude_self else counts
    order = Window.partitionBy("query_id").orderBy(F.desc("hits"), "id")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", "hits")


def search(sets: DataFrame, queries: DataFrame, k: int = 4, tables: int = 24, answers: int = 10, nodes: int = 4, strategy: str = "tree", depth: int = sketch.DEPTH, width: int = sketch.WIDTH, seed: int = 1, cap: int | None = None, exclude_self: bool = True, **options) -> DataFrame:
    """(query_id, rank, id, votes, upper): answers without a distance. For counts, votes and upper are the hits.

    exclude_self leaves out answers whose id is the query's; queries from another table set it to False."""
    buckets = build_bucket_index(sets, k, tables, nodes, seed, **options)
    keys = hash_queries(queries, k, tables, seed, **options)
    if strategy == "reservoir":
        buckets = build_reservoir_index(buckets, cap or 32)
    index = buckets if strategy in ("exact", "reservoir") else build_sketch_index(buckets, depth, width)
    return search_index(keys, index, answers, nodes, strategy, depth, width, exclude_self)


def search_index(keys: DataFrame, index: DataFrame, answers: int, nodes: int, strategy: str = "tree", depth: int = sketch.DEPTH, width: int = sketch.WIDTH, exclude_self: bool = True, **size) -> DataFrame:
    """Answers of query keys from a made (or stored) index: cells for tree, linear and multiway, bucket rows for exact and reservoir."""
    if strategy in ("exact", "reservoir"):
        return top_hits(exact_counts(keys, index, **size), answers, exclude_self).select("query_id", "rank", "id", F.col("hits").alias("votes"), F.col("hits").alias("upper"))
    return answer(global_merge(local_merge(keys, index, **size), nodes, strategy), answers, depth, width, exclude_self)


def search_one(keys: DataFrame, index: DataFrame, answers: int, nodes: int, strategy: str = "tree", depth: int = sketch.DEPTH, width: int = sketch.WIDTH) -> DataFrame:
    """One online query. Its keys, one a table, become literals, so that a stored index prunes files by table and row groups by key."""
    own = keys.select("query_id", "table_id", "bucket_key").collect()
    if len({r["query_id"] for r in own}) > 1:
        raise ValueError("search_one takes the keys of one query")
    few = index.where(F.col("bucket_key").isin([r["bucket_key"] for r in own]) & F.col("table_id").isin([r["table_id"] for r in own]))
    literal = keys.sparkSession.createDataFrame([tuple(r) for r in own], "query_id long, table_id int, bucket_key string")
    return search_index(literal, few, answers, nodes, strategy, depth, width, queries=1, tables=max(1, len(own)))


def answer(merged: DataFrame, answers: int, depth: int = sketch.DEPTH, width: int = sketch.WIDTH, exclude_self: bool = True) -> DataFrame:
    """(query_id, rank, id, votes, upper): the best of merged cells, but for the query itself."""
    if not exclude_self:
        return sketch.top_k(merged, ["query_id"], answers, depth, width).select("query_id", "rank", "id", "votes", "upper")
    top = sketch.top_k(merged, ["query_id"], answers + 1, depth, width).where("query_id <> id")
    order = Window.partitionBy("query_id").orderBy("rank")
    return top.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= answers).select("query_id", "rank", "id", "votes", "upper")


def with_similarity(pairs: DataFrame, data: DataFrame, queries: DataFrame, measure: str = "cosine") -> DataFrame:
    """pairs (query_id, id, …) with the exact similarity: only these rows' vectors are read again."""
    both = pairs.join(data.select("id", F.col("tokens").alias("_d")), "id").join(queries.select(F.col("id").alias("query_id"), F.col("tokens").alias("_q")), "query_id")
    f = cosine_sets if measure == "cosine" else jaccard
    return both.withColumn("similarity", f(F.col("_q"), F.col("_d"))).drop("_q", "_d")


def classic_lsh(sets: DataFrame, queries: DataFrame, k: int, tables: int, answers: int, min_hits: int = 1, seed: int = 1, measure: str = "cosine", **options) -> DataFrame:
    """Union of the buckets, exact distances on those with enough hits, the best by distance."""
    keyed = [key_lists(rows, k, tables, seed, **options) for rows in (sets, queries)]
    return pairs.most_similar(*keyed, answers, measure, min_hits=min_hits)


def within(data: DataFrame, queries: DataFrame, radius: float, measure: str = "cosine") -> DataFrame:
    """(query_id, id, distance) of all rows no farther than a radius below 1; rows that share no token are at distance 1."""
    if not 0 <= radius < 1:
        raise ValueError("radius must lie in [0, 1)")
    found = pairs.met(data, queries, measure, least=1 - radius)
    return found.select("query_id", "id", F.round(1 - pairs.similarity(measure), 6).alias("distance")).where(F.col("distance") <= radius)


def near_neighbor(found: DataFrame, data: DataFrame, queries: DataFrame, radius: float, factor: float, measure: str = "cosine") -> DataFrame:
    """(query_id, id, distance): the first answer of each query, if it is no farther than factor times radius; else no row."""
    first = with_similarity(found.where("rank = 1").select("query_id", "id"), data, queries, measure)
    return first.select("query_id", "id", F.round(1 - F.col("similarity"), 6).alias("distance")).where(F.col("distance") <= factor * radius)


def is_k_bounded(data: DataFrame, queries: DataFrame, radius: float, k: int, measure: str = "cosine") -> DataFrame:
    """(query_id, near, bounded): rows within the radius of each query that has any, and whether they are at most k."""
    return within(data, queries, radius, measure).groupBy("query_id").agg(F.count("*").alias("near")).withColumn("bounded", F.col("near") <= k)


def brute_force(data: DataFrame, queries: DataFrame, answers: int, measure: str = "cosine") -> DataFrame:
    return pairs.most_similar(data, queries, answers, measure)
