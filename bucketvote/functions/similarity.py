"""Exact similarities of sets and vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def jaccard(a: Column, b: Column) -> Column:
    both = F.size(F.array_intersect(a, b))
    return both / (F.size(a) + F.size(b) - both)


def cosine_sets(a: Column, b: Column) -> Column:
    return F.size(F.array_intersect(a, b)) / F.sqrt((F.size(a) * F.size(b)).cast("double"))


def cosine_dense(a: Column, b: Column) -> Column:
    def dot(x, y):
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def distance(kind: str, a: Column, b: Column) -> Column:
    if kind == "jaccard":
        return 1 - jaccard(a, b)
    if kind == "cosine":
        return 1 - cosine_sets(a, b)
    if kind == "euclidean":  # of the sets' indicator vectors
        both = F.size(F.array_intersect(a, b))
        return F.sqrt((F.size(a) + F.size(b) - 2 * both).cast("double"))
    raise ValueError(kind)


def shared_tokens(data: DataFrame, queries: DataFrame, measure: str = "cosine") -> DataFrame:
    """(query_id, id, similarity) of pairs that share a token, by a join on tokens; the pair with oneself is left out."""
    left = queries.select(F.col("id").alias("query_id"), F.size("tokens").alias("nq"), F.explode("tokens").alias("token"))
    right = data.select("id", F.size("tokens").alias("nd"), F.explode("tokens").alias("token"))
    both = left.join(right, "token").where("query_id <> id").groupBy("query_id", "id").agg(F.count("*").alias("both"), F.first("nq").alias("nq"), F.first("nd").alias("nd"))
    value = F.col("both") / F.sqrt((F.col("nq") * F.col("nd")).cast("double")) if measure == "cosine" else F.col("both") / (F.col("nq") + F.col("nd") - F.col("both"))
    return both.select("query_id", "id", value.alias("similarity"))


def weighted_cosine(vectors: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, id, similarity) of weighted sparse vectors (id, token, weight)."""
    norm = vectors.groupBy("id").agg(F.sqrt(F.sum(F.col("weight") * F.col("weight"))).alias("norm"))
    q = queries.select(F.col("id").alias("query_id"), "token", F.col("weight").alias("w"))
    dots = q.join(vectors, "token").where("query_id <> id").groupBy("query_id", "id").agg(F.sum(F.col("w") * F.col("weight")).alias("dot"))
    out = dots.join(norm, "id").join(norm.select(F.col("id").alias("query_id"), F.col("norm").alias("qn")), "query_id")
    return out.select("query_id", "id", (F.col("dot") / (F.col("norm") * F.col("qn"))).alias("similarity"))


#: Queries that are broadcast at most, rows of a part and queries of a block beyond.
FEW_QUERIES, PART_ROWS, BLOCK_QUERIES = 2_000, 20_000, 256


def dense_pairs(rows: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, id, similarity) of every query with every other row; both are (id, v).

    Counted queries are broadcast if they are few; else blocks of them meet parts of the rows, each pair in a task's reach.
    """
    q = queries.select(F.col("id").alias("query_id"), F.col("v").alias("q"))
    n = queries.count()
    if n <= FEW_QUERIES:
        met = rows.join(F.broadcast(q), F.col("id") != F.col("query_id"))
    else:
        parts, blocks = -(-rows.count() // PART_ROWS), -(-n // BLOCK_QUERIES)

        def dealt(df, key, own, n_own, other, n_other):
            placed = df.withColumn(own, F.pmod(F.xxhash64(key), F.lit(n_own)))
            return placed.withColumn(other, F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n_other - 1).cast("long"))))

        met = dealt(rows, "id", "part", parts, "block", blocks).join(dealt(q, "query_id", "block", blocks, "part", parts), ["part", "block"]).where("id <> query_id")
    return met.select("query_id", "id", cosine_dense(F.col("q"), F.col("v")).alias("similarity"))
