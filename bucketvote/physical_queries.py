"""Other physical forms of the same steps, sinks, user functions and plan checks as queries."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from .catalogue import DEPTH, K, NODES, TABLES, WIDTH, BC, asked, buckets, cells, doc_sets, event_ids, local, qkeys
from .operators import counters, sketch
from .operators import search as S
from .oracle import Build, num
from .plans.explain import exchanges, plan_contains, plan_text
from .registry import add
from .sources.shared import reachable, shared_folder, stored
from .sources.tables import load
from .streaming import growth as G


# merges of event types' sketches: few keys, so that every form may hold a whole sketch
def node_cells(s, d, nodes=4, width=64):
    rows = S.assign_nodes(event_ids(s, d).distinct(), nodes)
    return sketch.build_cells(rows, ["event_type", "node"], 2, width)


def node_cells_sql(nodes=4, width=64) -> str:
    b = Build("SELECT DISTINCT user_id id, event_type token FROM events WHERE user_id IS NOT NULL")
    b.add("ev", f"SELECT id, token event_type, CAST({num('id')} % {nodes} AS INTEGER) node FROM sets").add("sp", b.spread("ev", 2, width))
    least = num("concat_ws('/', id, \"row\")")
    b.add("cells", f'SELECT event_type, node, "row", col, CAST(count(*) AS BIGINT) total, min({{s: {least}, c: id}}).c cand, CAST(count(*) = 1 AS BIGINT) votes FROM sp GROUP BY ALL')
    return b.merge("merged", "cells", "event_type").select('SELECT event_type, "row", col, total, cand, votes FROM merged')


add("a06_tree_reduce", node_cells_sql())(lambda s, d: counters.reduced_cells(node_cells(s, d), ["event_type"]))
add("a04_partial_merge", node_cells_sql())(lambda s, d: sketch.merge_cells(node_cells(s, d), ["event_type"]))


def cogrouped(s, d):
    """Two nodes' sketches of a type merged in one cogroup."""
    made = node_cells(s, d, 2)
    return counters.cogrouped_merge(made.where("node = 0"), made.where("node = 1"), "event_type")


add("o30_cogroup", node_cells_sql(2))(cogrouped)


def everywhere(s, d):
    """What each node holds after the results are exchanged: cells and the sum of their totals."""
    merged = S.global_merge(local(s, d), NODES, "tree")
    return S.on_every_node(merged, NODES).groupBy("node").agg(F.count("*").alias("cells"), F.sum("total").alias("total"))


add("a07_every_node", BC().local().tree(NODES).select(f"SELECT CAST(r.n AS INTEGER) node, count(*) cells, CAST(sum(total) AS BIGINT) total FROM merged, range({NODES}) r(n) GROUP BY r.n"))(everywhere)

# tops of packed sketches, as an aggregate and as a table function
TOP = BC().local().merge("merged", "local_cells", "query_id").top(5, DEPTH, WIDTH, False)


def merged_cells(s, d):
    return S.global_merge(local(s, d), NODES, "multiway")


add("o28_sketch_top_k", TOP.select('SELECT query_id, "rank", id FROM answers'))(lambda s, d: counters.packed_top_k(merged_cells(s, d), ["query_id"], 5, DEPTH, WIDTH))


def top_table(s, d):
    from .functions.udtf import sketch_top

    s.udtf.register("sketch_top", sketch_top)
    name = f"cells_{uuid.uuid4().hex}"
    merged_cells(s, d).createOrReplaceTempView(name)
    return s.sql(f"SELECT * FROM sketch_top(TABLE({name}) PARTITION BY (query_id), 5, {DEPTH}, {WIDTH})")


add("o29_sketch_top", TOP.select('SELECT query_id, "rank", id, upper, votes FROM answers'))(top_table)


# estimates of counting sketches
def counted(s, d):
    return event_ids(s, d).groupBy("event_type", "id").agg(F.count("*").alias("n"))


def builtin_estimates(s, d, eps=0.05):
    """The built-in count-min sketch asked for every id: how many ids, and how many estimates fall below the truth (none may)."""
    packed = event_ids(s, d).groupBy("event_type").agg(F.count_min_sketch("id", F.lit(eps), F.lit(0.95), F.lit(1)).alias("packed"))
    true = counted(s, d)
    # a sketch a type, of a size that eps fixes
    made = counters.packed_estimates(true.join(packed, "event_type").select(F.col("event_type").alias("key"), "packed", "id"))
    both = true.join(made, (true["event_type"] == made["key"]) & (true["id"] == made["id"]))
    return both.groupBy("event_type").agg(F.count("*").alias("ids"), F.sum("n").alias("total"), F.count_if(F.col("estimate") < F.col("n")).alias("below"))


add("s08_builtin_estimates", "SELECT event_type, count(DISTINCT user_id) ids, count(*) total, CAST(0 AS BIGINT) AS below FROM events WHERE user_id IS NOT NULL GROUP BY event_type")(builtin_estimates)
EV = Build("SELECT user_id id, event_type token FROM events WHERE user_id IS NOT NULL")
EV.add("ev", "SELECT id, token event_type FROM sets").add("sp", EV.spread("ev", 3, 64))
SIGN = "(1 - 2 * (" + num("concat_ws('/', id, \"row\")") + " % 2))"
EV.add("signed", f'SELECT event_type, "row", col, sum({SIGN}) total FROM sp GROUP BY ALL').add("ids", "SELECT DISTINCT event_type, id FROM ev").add("at_ids", EV.spread("ids", 3, 64))
add("s10_estimates", EV.select(f'SELECT a.event_type, id, CAST(median({SIGN.replace(chr(34) + "row" + chr(34), "a." + chr(34) + "row" + chr(34))} * coalesce(total, 0)) AS DOUBLE) estimate FROM at_ids a LEFT JOIN signed g ON g.event_type = a.event_type AND g."row" = a."row" AND g.col = a.col GROUP BY ALL'))(
    lambda s, d: sketch.count_sketch_estimate(sketch.count_sketch(event_ids(s, d), ["event_type"], 3, 64), event_ids(s, d).select("event_type", "id").distinct(), ["event_type"], 3, 64)
)


#: Ids that the built-in top-k sketch tracks, and ids of a group on average: a hash group then holds fewer than it tracks, so its counts are exact.
TRACKED, GROUP_IDS = 10_000, 6_000


def combined_top(s, d, k=5, group_ids=GROUP_IDS):
    """Counts of the built-in top k, accumulated a node, combined over nodes, then estimated; ids of equal counts may stand in any order, so counts are reported.

    A sketch is exact while it tracks every id. Ids are counted and dealt into groups that fit; an id lies in one group,
    so the best of the groups' best are the best of all.
    """
    rows = S.assign_nodes(event_ids(s, d), NODES)
    groups = max(1, -(-rows.agg(F.count_distinct("id")).first()[0] // group_ids))
    dealt = rows.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(groups)))
    states = dealt.groupBy("event_type", "part", "node").agg(F.expr(f"approx_top_k_accumulate(id, {TRACKED})").alias("state"))
    top = states.groupBy("event_type", "part").agg(F.expr(f"approx_top_k_combine(state, {TRACKED})").alias("state")).select("event_type", F.expr(f"approx_top_k_estimate(state, {k})").alias("top"))
    best = top.select("event_type", F.explode("top.count").alias("n"))
    place = F.row_number().over(Window.partitionBy("event_type").orderBy(F.desc("n"))) - 1
    return best.withColumn("place", place).where(F.col("place") < k).select("event_type", "place", "n")


add("s12_combined_top_k", "SELECT event_type, CAST(row_number() OVER (PARTITION BY event_type ORDER BY n DESC) - 1 AS INTEGER) place, n FROM (SELECT event_type, user_id, count(*) n FROM events WHERE user_id IS NOT NULL GROUP BY ALL) QUALIFY place < 5")(combined_top)


# formats, sinks, caching
def text_lines(s, d):
    path = shared_folder(s, "text")
    load(s, d, "part").select("p_name").where("p_name is not null").write.text(path)
    return s.read.text(path)


add("o02_text", "SELECT p_name AS value FROM part WHERE p_name IS NOT NULL")(text_lines)


def bucketed_join(s, d, buckets=8):
    """Orders and customers written in buckets of the customer's key: their join needs no shuffle."""
    held = {}
    for table, key in (("orders", "o_custkey"), ("customer", "c_custkey")):
        name = f"bucketed_{table}_{uuid.uuid4().hex}"
        columns = [key, "o_orderkey"] if table == "orders" else [key, "c_mktsegment"]
        load(s, d, table).select(*columns).write.bucketBy(buckets, key).sortBy(key).option("path", shared_folder(s, name)).saveAsTable(name)
        held[table] = s.table(name)
    both = held["orders"].hint("merge").join(held["customer"], F.col("o_custkey") == F.col("c_custkey"))
    return both.groupBy("c_mktsegment").agg(F.count("*").alias("n"))


add("o02_bucketed", "SELECT c_mktsegment, count(*) n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL")(bucketed_join)


def typed_stream(s, d):
    return G.follow(s, f"{d}/events.parquet").groupBy("event_type").agg(F.count("*").alias("n"))


PER_TYPE = "SELECT event_type, count(*) n FROM events GROUP BY ALL"
add("st06_complete", PER_TYPE)(lambda s, d: G.latest(G.drain(typed_stream(s, d), "complete", "complete"), ["event_type"]))
add("st06_update", PER_TYPE)(lambda s, d: G.latest(G.drain(typed_stream(s, d), "update", "update"), ["event_type"]))


def in_memory(s, d):
    """The memory sink: for answers of a few rows, here one a type."""
    name = f"per_type_{uuid.uuid4().hex}"
    log = shared_folder(s, "memory-sink")
    typed_stream(s, d).writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
    return s.table(name)


add("o03_memory_sink", PER_TYPE)(in_memory)


def cached_twice(s, d):
    """Query keys and counts from one persisted table of sets, which is given back before the answer is read."""
    rows = doc_sets(s, d).persist()
    try:
        return stored(S.search(rows, asked(rows), K, TABLES, 10, NODES, "exact"), "answers")
    finally:
        rows.unpersist()


def checkpointed(s, d):
    """The same from a reliable checkpoint."""
    reachable(s)
    rows = doc_sets(s, d).checkpoint()
    return S.search(rows, asked(rows), K, TABLES, 10, NODES, "exact")


ANSWERS = 'SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) AS INTEGER) AS "rank", id, hits votes, hits AS upper FROM counts WHERE query_id <> id QUALIFY "rank" <= 10'
for _name, _run in {"o31_persist": cached_twice, "o31_checkpoint": checkpointed}.items():
    add(_name, Build().buckets(K, TABLES, NODES).queries().counts().select(ANSWERS))(_run)


# user functions
def best_three(s, d):
    """Three best documents a query, with both sets as x and y."""
    rows = doc_sets(s, d)
    top = S.brute_force(rows, asked(rows), 3, "jaccard").drop("similarity")
    return top.join(rows.withColumnRenamed("tokens", "x"), "id").join(rows.select(F.col("id").alias("query_id"), F.col("tokens").alias("y")), "query_id")


def scalar_function(s, d):
    """Jaccard by a plain Python function, for comparison with the built-in expression."""
    jac = F.udf(lambda x, y: len({*x} & {*y}) / max(1, len({*x} | {*y})), "double")
    return best_three(s, d).select("query_id", "id", F.round(jac("x", "y"), 6).alias("similarity"))


def sql_function(s, d):
    """Jaccard as a function declared in SQL, which the optimizer inlines."""
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_jaccard(x ARRAY<STRING>, y ARRAY<STRING>) RETURNS DOUBLE RETURN size(array_intersect(x, y)) / size(array_union(x, y))")
    return best_three(s, d).select("query_id", "id", F.expr("round(set_jaccard(x, y), 6)").alias("similarity"))


JAC = "shared / CAST(na + nb - shared AS DOUBLE)"
for _name, _run in {"o27_scalar_function": scalar_function, "o27_sql_function": sql_function}.items():
    add(_name, Build().asked().pairs().select(f"SELECT query_id, id, round({JAC}, 6) similarity FROM sim_rows QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round({JAC}, 9) DESC, id) <= 3"))(_run)


# plans
def plan_claims(s, d):
    """Claims on physical plans, read from the plans of this session."""
    keys, index = qkeys(s, d), buckets(s, d)
    near = S.local_merge(keys, S.build_sketch_index(index, DEPTH, WIDTH))
    tree, linear = S.global_merge(near, 4, "tree"), S.global_merge(near, 4, "linear")
    rows = doc_sets(s, d)
    found = S.search(rows, asked(rows), K, TABLES, 10, NODES, "tree", DEPTH, WIDTH)
    scan = plan_text(load(s, d, "lineitem").where("l_quantity > 40").select("l_orderkey"))
    claims = {
        "few query keys are broadcast": plan_contains(S.probe(keys, index, queries=1, tables=TABLES), "BroadcastHashJoin"),
        "a bucket index has no aggregation": not plan_contains(index, "HashAggregate"),
        "a tree of four nodes takes one shuffle more than a linear merge": exchanges(tree) == exchanges(linear) + 1,
        "a sketch search computes no distance": "array_intersect" not in plan_text(found),
        "classic search computes distances": "array_intersect" in plan_text(S.with_similarity(S.exact_counts(keys, index), rows, asked(rows))),
        "filters and columns reach the scan": "GreaterThan(l_quantity,40" in scan and "l_comment" not in scan,
    }
    return s.createDataFrame(list(claims.items()), "claim string, holds boolean")


CLAIMS = ("few query keys are broadcast", "a bucket index has no aggregation", "a tree of four nodes takes one shuffle more than a linear merge", "a sketch search computes no distance", "classic search computes distances", "filters and columns reach the scan")
add("o32_plan_claims", " UNION ALL ".join(f"SELECT '{c}' AS claim, true AS holds" for c in CLAIMS))(plan_claims)
