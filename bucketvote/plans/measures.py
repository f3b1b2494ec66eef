"""Accuracy and cost measures."""

from __future__ import annotations

from time import perf_counter

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import jaccard_estimate
from ..operators import search as S


def similarity_at_k(answers: DataFrame, data: DataFrame, queries: DataFrame, ks: tuple[int, ...] = (1, 64), missing: str = "ignore") -> DataFrame:
    """(k, s_at_k, coverage, queries): mean over queries of the mean cosine of the first k answers.

    `ignore` leaves out queries without an answer and averages what came back; `zero` counts what is missing as 0.
    """
    scored = S.with_similarity(answers.select("query_id", "rank", "id"), data, queries)
    n = queries.count()
    wanted = scored.withColumn("k", F.explode(F.array(*[F.lit(k) for k in ks]))).where("rank <= k")
    per = wanted.groupBy("k", "query_id").agg(F.sum("similarity").alias("s"), F.count("*").alias("n"))
    value = F.avg(F.col("s") / F.col("n")) if missing == "ignore" else F.sum(F.col("s") / F.col("k")) / n
    return per.groupBy("k").agg(F.round(value, 6).alias("s_at_k"), F.round(F.sum("n") / (F.first("k") * n), 6).alias("coverage"), F.lit(n).cast("long").alias("queries"))


def recall_at_k(answers: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    good = truth.where(F.col("rank") <= k).select("query_id", "id")
    hit = good.join(answers.where(F.col("rank") <= k).select("query_id", "id"), ["query_id", "id"], "left_semi")
    return good.agg(F.count("*").alias("wanted")).crossJoin(hit.agg(F.count("*").alias("found"))).select(F.lit(k).alias("k"), "found", "wanted", F.round(F.col("found") / F.col("wanted"), 6).alias("recall"))


def random_pair_similarity(sets: DataFrame, sample: int = 200) -> DataFrame:
    """Mean cosine over the pairs of the `sample` ids of least hash."""
    from ..functions.hashing import token_number

    some = sets.orderBy(token_number(F.col("id")), "id").limit(sample)
    pairs = some.alias("a").join(some.alias("b"), F.col("a.id") < F.col("b.id"))
    from ..functions.similarity import cosine_sets

    return pairs.agg(F.count("*").alias("pairs"), F.round(F.avg(cosine_sets(F.col("a.tokens"), F.col("b.tokens"))), 6).alias("mean_cosine"))


def index_stats(buckets: DataFrame) -> DataFrame:
    """Buckets, ids, largest, singletons and share of ids in buckets of over 8 ids, per table."""
    sizes = buckets.groupBy("table_id", "bucket_key").agg(F.count("*").alias("n"))
    return sizes.groupBy("table_id").agg(
        F.count("*").alias("buckets"), F.sum("n").alias("ids"), F.max("n").alias("largest"), F.sum((F.col("n") == 1).cast("long")).alias("singletons"),
        F.round(F.sum(F.when(F.col("n") > 8, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias("heavy_share"),
    )


def skew_report(buckets: DataFrame) -> DataFrame:
    """(table_id, buckets, largest, p99, gini) of bucket sizes. Gini comes from the histogram of sizes, so its window holds one row per size."""
    sizes = buckets.groupBy("table_id", "bucket_key").agg(F.count("*").alias("n")).groupBy("table_id", "n").agg(F.count("*").alias("c"))
    up = Window.partitionBy("table_id").orderBy("n").rowsBetween(Window.unboundedPreceding, 0)
    ranked = sizes.withColumn("upto", F.sum("c").over(up))
    # the c buckets of one size hold the places upto - c + 1 to upto
    places = F.col("c") * (2 * F.col("upto") - F.col("c") + 1) / 2
    all_n = F.sum(F.col("n") * F.col("c"))
    per = ranked.groupBy("table_id").agg(F.sum("c").alias("buckets"), F.max("n").alias("largest"), F.sum(places * F.col("n")).alias("w"), all_n.alias("ids"), F.percentile("n", 0.99, F.col("c")).alias("p99"))
    gini = 2 * F.col("w") / (F.col("buckets") * F.col("ids")) - (F.col("buckets") + 1) / F.col("buckets")
    return per.select("table_id", "buckets", "largest", F.round("p99", 6).alias("p99"), F.round(gini, 6).alias("gini"))


def quality_gap(quality: DataFrame, ideal: DataFrame) -> DataFrame:
    """quality (strategy, nodes, k, s_at_k, …) with how far it lies below ideal (k, s_at_k)."""
    return quality.join(ideal.select("k", F.col("s_at_k").alias("ideal")), "k").withColumn("gap", F.round(F.col("ideal") - F.col("s_at_k"), 6))


def scaling(times: DataFrame, by: list[str]) -> DataFrame:
    """times (…, nodes, seconds) with the speed-up over the fewest nodes and its share of the ideal."""
    w = Window.partitionBy(*by).orderBy("nodes")
    faster = F.first("seconds").over(w) / F.col("seconds")
    return times.withColumn("speedup", F.round(faster, 3)).withColumn("efficiency", F.round(faster / (F.col("nodes") / F.first("nodes").over(w)), 3))


def estimate_sensitivity(sig: DataFrame, pairs: DataFrame, near: float, far: float) -> DataFrame:
    """(p1, p2): mean agreement of signatures over pairs (query_id, id, similarity) of at least `near` and at most `far`."""
    both = pairs.join(sig.select("id", F.col("sig").alias("s1")), "id").join(sig.select(F.col("id").alias("query_id"), F.col("sig").alias("s2")), "query_id")
    rate = jaccard_estimate(F.col("s1"), F.col("s2"))
    return both.agg(F.round(F.avg(F.when(F.col("similarity") >= near, rate)), 6).alias("p1"), F.round(F.avg(F.when(F.col("similarity") <= far, rate)), 6).alias("p2"))


def node_imbalance(buckets: DataFrame) -> DataFrame:
    per = buckets.groupBy("node").agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("nodes"), F.max("n").alias("most"), F.round(F.max("n") / F.avg("n"), 6).alias("imbalance"))


def merge_cost(keys: DataFrame, buckets: DataFrame, nodes: int) -> DataFrame:
    """Per query: sketches merged on nodes, rounds of the tree, and merges of a linear gather."""
    reached = S.probe(keys, buckets).groupBy("query_id").agg(F.count_distinct("node", "table_id", "bucket_key").alias("sketches"))
    return reached.select("query_id", "sketches", F.lit(S.tree_rounds(nodes)).cast("long").alias("rounds"), F.lit(nodes - 1).cast("long").alias("linear_merges"))


def communication_volume(local: DataFrame, counts_local: DataFrame, nodes: int) -> DataFrame:
    """Rows that leave their node: cells by the tree's rounds (an upper bound: no cell meets another) and the gather, ids by exact counting."""
    cells = local.where("node > 0").agg(F.count("*").alias("n")).select(F.lit("linear").alias("strategy"), "n")
    ids = counts_local.where("node > 0").agg(F.count("*").alias("n")).select(F.lit("exact").alias("strategy"), "n")
    out = cells.unionByName(ids)
    left, now, sent = nodes, local.select("query_id", "node", "row", "col").distinct(), None
    while left > 1:
        move = now.where("node % 2 = 1").agg(F.count("*").alias("n"))
        sent = move if sent is None else sent.union(move)
        now = now.select("query_id", F.floor(F.col("node") / 2).cast("int").alias("node"), "row", "col").distinct()
        left = -(-left // 2)
    return out.unionByName(sent.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).select(F.lit("tree").alias("strategy"), "n")) if sent is not None else out


def footprint(buckets: DataFrame, cells: DataFrame) -> DataFrame:
    b = buckets.agg(F.count("*").alias("n")).select(F.lit("ids").alias("kind"), "n", (F.col("n") * 8).alias("bytes"))
    return b.unionByName(cells.agg(F.count("*").alias("n")).select(F.lit("cells").alias("kind"), "n", (F.col("n") * 24).alias("bytes")))


def sketch_error(top: DataFrame, counts: DataFrame) -> DataFrame:
    """Over reported ids: how far the bounds lie from the true hits, and whether they hold."""
    both = top.join(counts, ["query_id", "id"], "left").withColumn("hits", F.coalesce("hits", F.lit(0)))
    return both.agg(F.count("*").alias("reported"), F.sum(((F.col("votes") <= F.col("hits")) & (F.col("hits") <= F.col("upper"))).cast("long")).alias("inside"), F.round(F.avg(F.col("upper") - F.col("hits")), 6).alias("mean_over"), F.round(F.avg(F.col("hits") - F.col("votes")), 6).alias("mean_under"))


def timed(df: DataFrame) -> float:
    """Seconds to make all rows of a DataFrame, written nowhere."""
    start = perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return perf_counter() - start
