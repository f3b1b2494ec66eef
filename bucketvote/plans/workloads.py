"""The experiments on the given tables: each takes sets and returns a report. Indexes are stored once and reused over a sweep."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import hashing
from ..operators import cells, hits, votes
from ..operators import search as S
from ..sources.shared import dropped, stored
from . import measures


def together(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def rows_of(spark, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def at_nodes(keys: DataFrame, nodes: int) -> DataFrame:
    return S.assign_nodes(keys, nodes).select("node", "table_id", "bucket_key", "id")


class Trial:
    """Sets, queries and their keys, each written once."""

    def __init__(self, rows: DataFrame, queries: DataFrame, k: int, tables: int, **family):
        self.rows, self.queries = stored(rows, "sets"), stored(queries, "queries")
        self.n, self.tables = self.queries.count(), tables
        self.keys = stored(hashing.keys_of(self.rows, k, tables, **family), "keys")
        self.asked = stored(S.hash_queries(self.queries, k, tables, **family), "query-keys")

    def index(self, nodes: int, depth: int = 2, width: int = 1024, strategy: str = "tree", cap: int = 32) -> DataFrame:
        b = at_nodes(self.keys, nodes)
        if strategy == "exact":
            return b  # the keys are stored, and a row's node is made from its id
        return stored(S.build_reservoir_index(b, cap) if strategy == "reservoir" else S.build_sketch_index(b, depth, width), "index")

    def search(self, index: DataFrame, answers: int, nodes: int, strategy: str, depth: int = 2, width: int = 1024) -> DataFrame:
        return S.search_index(self.asked, index, answers, nodes, strategy, depth, width, queries=self.n, tables=self.tables)

    def quality(self, found: DataFrame, ks: tuple[int, ...], missing: str = "ignore") -> DataFrame:
        return measures.similarity_at_k(found, self.rows, self.queries, ks, missing)


class Batch:
    """A trial whose indexes are made and searched inside tasks; the index of a number of nodes is stored whole and freed by `free`."""

    def __init__(self, rows: DataFrame, queries: DataFrame, k: int, tables: int, depth: int = 2, width: int = 1024):
        self.rows, self.queries = stored(rows, "sets"), stored(queries, "queries")
        self.n, self.way, self.size = self.queries.count(), (k, tables), (depth, width)
        self.known = votes.known_ids(self.rows)

    def index(self, nodes: int) -> str:
        """Ids and sketch cells of all buckets of every node."""
        return votes.write_index(self.rows, self.known, *self.way, nodes, *self.size)

    def search(self, index: str, answers: int, nodes: int, strategy: str) -> DataFrame:
        return votes.search_stored(self.queries, index, self.known, *self.way, nodes, answers, *self.size, strategy)

    def free(self, index: str) -> None:
        dropped(index)


#: The node counts of the scaling experiments.
EVERY_NODES = (2, 4, 6, 8, 10, 12, 14, 16)


def quality_over_nodes(trial: Trial, nodes=EVERY_NODES, ks=(1, 64), depth=2, width=1024) -> DataFrame:
    """S@k of tree, linear and exact by nodes, with the gap to brute force."""
    out = []
    for m in nodes:
        cells, ids = trial.index(m, depth, width), trial.index(m, strategy="exact")
        for strategy in ("tree", "linear", "exact"):
            found = trial.search(ids if strategy == "exact" else cells, max(ks), m, strategy, depth, width)
            out.append(trial.quality(found, ks).select(F.lit(strategy).alias("strategy"), F.lit(m).alias("nodes"), "k", "s_at_k", "coverage", "queries"))
    ideal = trial.quality(S.brute_force(trial.rows, trial.queries, max(ks)), ks)
    # one table a node count: its three plans run side by side, and no plan grows with the sweep
    parts = [stored(together(out[i : i + 3]), "quality") for i in range(0, len(out), 3)]
    return measures.quality_gap(together(parts), stored(ideal, "ideal"))


def quality_in_tasks(rows: DataFrame, queries: DataFrame, k: int, tables: int, nodes=EVERY_NODES, ks=(1, 64), depth=2, width=1024) -> DataFrame:
    """`quality_over_nodes` with cells built, merged and ranked inside tasks; each pair of a query and an answer is compared once, however many searches give it."""
    rows, queries = stored(rows, "sets"), stored(queries, "queries")
    n, name = queries.count(), F.col("strategy")
    found = votes.searches(rows, queries, k, tables, tuple(nodes), max(ks), depth, width)
    best = S.brute_force(rows, queries, max(ks)).select(F.lit("ideal").alias("strategy"), F.lit(0).alias("nodes"), "query_id", "rank", "id")
    found = stored(found.unionByName(best), "found")
    scored = found.join(hits.graded_pairs(found.select("query_id", "id").distinct(), rows, queries), ["query_id", "id"])
    firsts = [F.sum(F.when(F.col("rank") <= k, F.col("similarity"))).alias(f"s{k}") for k in ks] + [F.count(F.when(F.col("rank") <= k, 1)).alias(f"n{k}") for k in ks]
    per = scored.groupBy("strategy", "nodes", "query_id").agg(*firsts)
    means = [F.struct(F.lit(k).alias("k"), F.round(F.avg(F.col(f"s{k}") / F.col(f"n{k}")), 6).alias("s_at_k"), F.round(F.sum(f"n{k}") / (k * n), 6).alias("coverage")) for k in ks]
    # a few rows, read twice
    graded = stored(per.groupBy("strategy", "nodes").agg(F.array(*means).alias("m")).select("strategy", "nodes", F.inline("m")), "quality")
    exact = graded.where(name == "exact").withColumn("nodes", F.explode(F.array(*[F.lit(m) for m in nodes])))
    quality = graded.where(name.isin("tree", "linear")).unionByName(exact).withColumn("queries", F.lit(n).cast("long"))
    return measures.quality_gap(quality, graded.where(name == "ideal"))


def index_scaling(spark, families: dict[str, tuple[DataFrame, int, int]], nodes=EVERY_NODES, depth=2, width=1024) -> DataFrame:
    """Seconds to build sketch indexes, a node being a partition of the sets, dealt anew for each count; speed-up over the fewest nodes."""
    times = []
    for name, (rows, k, tables) in families.items():
        held = stored(rows, "sets")
        n = held.count()
        for m in nodes:
            built = cells.node_index(held, k, tables, m, depth, width, n)
            times.append((name, m, round(measures.timed(built), 3)))
            del built
            spark.sparkContext._jvm.System.gc()  # else the dealt rows of every build stay on disk to the end
    return measures.scaling(rows_of(spark, times, "family string, nodes int, seconds double"), ["family"])


def query_scaling(spark, trials: dict[str, Callable[[], Batch]], nodes=EVERY_NODES, answers=64) -> DataFrame:
    """Milliseconds a query, by nodes and strategy, from stored indexes; one batch each, after one that warms up. An index is kept while its node count is timed."""
    times = []
    for name, made in trials.items():
        trial = made()
        for m in nodes:
            index = trial.index(m)
            for strategy in ("tree", "linear", "exact"):
                run = trial.search(index, answers, m, strategy)
                measures.timed(run)
                times.append((name, strategy, m, trial.n, round(1000 * measures.timed(run) / max(1, trial.n), 3)))
            trial.free(index)
            spark.sparkContext._jvm.System.gc()  # else the dealt rows of every index stay on disk to the end
    return rows_of(spark, times, "family string, strategy string, nodes int, queries int, ms_per_query double")


#: Fixed value: rows of the published large run.
PUBLISHED_ROWS = 4_195_197_692


def large_scale(spark, rows: DataFrame, queries: DataFrame, nodes=(5, 10, 15, 20), k=4, tables=32, depth=2, width=1024) -> DataFrame:
    """Index seconds and query milliseconds on the largest table, by nodes, and what the largest node count's index
    would take at the published size, in proportion to rows and cores: a build is one pass over the rows and one shuffle of its cells."""
    trial, times = Trial(rows, queries, k, tables), []
    n, cores = trial.rows.count(), spark.sparkContext.defaultParallelism
    for m in nodes:
        built = measures.timed(S.build_sketch_index(S.build_bucket_index(trial.rows, k, tables, m), depth, width))
        run = trial.search(trial.index(m, depth, width), 64, m, "tree", depth, width)
        measures.timed(run)
        core_seconds_a_million = built * cores / max(1, n) * 1e6
        times.append((m, n, round(built, 3), round(1000 * measures.timed(run) / max(1, trial.n), 3), round(core_seconds_a_million, 3), round(core_seconds_a_million * PUBLISHED_ROWS / 1e6 / 3600, 1)))
    return rows_of(spark, times, "nodes int, rows long, index_seconds double, ms_per_query double, core_seconds_per_million double, published_core_hours double")


def sketch_sizes(trial: Trial, depths=(1, 2, 3, 4), widths=(64, 128, 256, 512, 1024, 2048, 4096), answers=10, nodes=4) -> DataFrame:
    """Quality and error of the sketch by depth and width."""
    exact = stored(S.exact_counts(trial.asked, at_nodes(trial.keys, nodes), queries=trial.n, tables=trial.tables), "counts")
    out = []
    for depth in depths:
        for width in widths:
            cells = S.build_sketch_index(at_nodes(trial.keys, nodes), depth, width)
            found = stored(trial.search(cells, answers, nodes, "tree", depth, width), "found")
            error = measures.sketch_error(found, exact)
            out.append(trial.quality(found, (answers,)).crossJoin(error).select(F.lit(depth).alias("depth"), F.lit(width).alias("width"), "s_at_k", "coverage", "mean_over", "mean_under"))
    return together(out)


def named(made: DataFrame, *values: tuple) -> DataFrame:
    """made (way, …) with columns (name, values by way) in place of the way's number."""
    return made.withColumns({name: F.element_at(F.array(*[F.lit(x) for x in each]), F.col("way") + 1) for name, each in values}).drop("way")


def reservoirs(rows: DataFrame, queries: DataFrame, k=1, tables=(8, 16, 24, 32), caps=(8, 32, 128), answers=10, nodes=4) -> DataFrame:
    """Quality by the number of tables and the cap of reservoir buckets, beside uncapped buckets (cap 0); all in one pass."""
    made = hits.quality(rows, queries, [hits.Way(k, t) for t in tables], answers, caps, nodes)
    return named(made, ("tables", tables)).select("tables", "cap", "s_at_k", "coverage")


def hash_families(rows: DataFrame, queries: DataFrame, k=1, tables=24, answers=10) -> DataFrame:
    """Quality of exact counting by hash family and way of filling empty bins, with the hashes a token costs; all in one pass."""
    ways = {"minhash": {"family": "minhash"}, "per_bin": {}, "rotation": {"coin": "always_right"}, "closest": {"coin": "closest_side"}, "offset": {"offset": True}, "interleave": {"layout": "interleave"}}
    cost = [k * tables if name == "minhash" else 1 for name in ways]
    made = hits.quality(rows, queries, [hits.Way(k, tables, options) for options in ways.values()], answers)
    return named(made, ("family", ways), ("hashes_per_token", cost)).select("family", "hashes_per_token", "s_at_k", "coverage")


def parameter_sweep(rows: DataFrame, queries: DataFrame, settings: tuple[tuple[int, int], ...], answers=10) -> DataFrame:
    """Quality, coverage and candidates a query of exact counting by settings (K, L); all in one pass."""
    made = hits.quality(rows, queries, [hits.Way(k, t) for k, t in settings], answers)
    return named(made, ("k", [k for k, _ in settings]), ("tables", [t for _, t in settings])).select("k", "tables", "s_at_k", "coverage", "candidates")
