"""Streams, classes, counters, table function and searches: against DuckDB, brute force and stated bounds."""

import random
from collections import Counter

import duckdb
import pytest
from pyspark.sql import functions as F

from bucketvote.every import QUERIES
from bucketvote.operators import counters, duplicates, sketch
from bucketvote.operators import search as S
from bucketvote.sources.tables import TABLES, balanced

SOME = ["st02_session", "st04_late_data", "s14_stream_cells", "w16_stream_totals", "st05_stream_static_search", "q12_classes", "o09_range_join", "o10_interval_join", "c12_skew", "q10_near_neighbor", "q11_bounded", "q13_search_one", "w11_communication", "a05_packed_merge", "o29_table_function", "s13_mergeability", "a06_tree_reduce", "o28_sketch_top_k", "o29_sketch_top", "o30_cogroup", "s08_builtin_estimates", "s10_estimates", "o02_bucketed", "st06_complete", "o27_sql_function", "o32_plan_claims"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, small, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    a, b = QUERIES[name].run(spark, small).toPandas(), con.execute(QUERIES[name].sql).df()
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)
    plain = [x[cols].astype(str).sort_values(cols).reset_index(drop=True) for x in (a, b)]
    assert plain[0].equals(plain[1])


def classes_by_force(sets, least):
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in sets:
        for j in sets:
            if i < j and len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= least:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {i: find(i) for i in sets}


def test_classes_of_copies_and_chains(spark):
    rng = random.Random(5)
    sets = {i: frozenset(f"c{j}" for j in range(30)) for i in range(100, 160)}  # equal rows
    sets |= {i: frozenset(f"s{j}" for j in range(i, i + 40)) for i in range(40)}  # each is near the next only
    sets |= {200 + i: frozenset(f"r{rng.randrange(10**6)}" for _ in range(20)) for i in range(30)}
    rows = spark.createDataFrame([(i, sorted(t)) for i, t in sets.items()], "id long, tokens array<string>")
    got = {r["id"]: r["class_id"] for r in duplicates.classes(rows, 1, 32, 0.8).collect()}
    assert got == classes_by_force(sets, 0.8)
    assert duplicates.links(rows.where("id between 100 and 159"), 1, 4).count() == 0


def test_components_of_a_long_path_and_nothing(spark):
    path = spark.range(200).select(F.col("id").alias("id_a"), (F.col("id") + 1).alias("id_b"))
    got = duplicates.components(path).collect()
    assert len(got) == 201 and {r["class_id"] for r in got} == {0}
    assert duplicates.components(path.where("false")).count() == 0
    empty = spark.createDataFrame([], "id long, tokens array<string>")
    assert duplicates.classes(empty, 2, 4).count() == 0


@pytest.mark.parametrize("make", [lambda r: counters.frequent_counters(r, "k", 8), lambda r: counters.lossy_counting(r, "k", 0.05)])
def test_counter_bounds(spark, make):
    rng = random.Random(2)
    data = [("a" if rng.random() < 0.8 else "b", int(rng.paretovariate(0.7))) for _ in range(5000)]
    true = Counter(data)
    size = Counter(k for k, _ in data)
    got = make(spark.createDataFrame(data, "k string, id long").repartition(5)).collect()
    found = {(r["key"], r["id"]) for r in got}
    assert all(r["n"] <= true[r["key"], r["id"]] <= r["n"] + r["slack"] for r in got)
    assert {x for x, n in true.items() if n >= 0.2 * size[x[0]]} <= found


def test_merges_keep_totals_in_every_order(spark):
    rng = random.Random(7)
    rows = [(1, node, 0, c, rng.randrange(1, 9), rng.randrange(20), 0) for node in range(7) for c in range(5)]
    cells = spark.createDataFrame([(*r[:6], min(r[4], 1)) for r in rows], "query_id long, node int, row int, col int, total long, cand long, votes long")
    true = Counter()
    for r in rows:
        true[r[3]] += r[4]
    for merged in (S.global_merge(cells, 7, "tree"), S.global_merge(cells, 7, "tree", 3), S.global_merge(cells, 7, "linear"), S.global_merge(cells, 7, "multiway")):
        assert {r["col"]: r["total"] for r in merged.collect()} == true
    assert {k[2]: v[0] for k, v in counters.tree_reduced(cells, ["query_id"]).items()} == true
    assert sketch.merge_cells(cells.where("false"), ["query_id"]).count() == 0


def test_limits_and_plans(spark, small):
    from bucketvote.catalogue import asked, doc_sets

    rows = doc_sets(spark, small)
    with pytest.raises(ValueError):
        S.within(rows, asked(rows, 2), 1.0)
    with pytest.raises(ValueError):
        S.search_one(S.hash_queries(asked(rows, 2), 2, 4), rows, 1, 1)
    plan = balanced(spark.read.parquet(f"{small}/documents.parquet")).where("lang = 'en'").select("doc_id")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(lang,en)" in plan and "text" not in plan.split("ReadSchema")[-1]


def test_contamination_finds_every_document(spark, tmp_path):
    from bucketvote.every import QUERIES

    passage = " ".join(f"p{i}" for i in range(20))
    docs = [(1, passage), (2, " ".join(f"x{i}" for i in range(500)) + " " + passage), (3, "p0 p1 p2 p3 other words"), (4, None)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(7, passage), (8, "not in any")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = QUERIES["w14_contamination"].run(spark, str(tmp_path)).collect()
    assert {(r["item_id"], r["doc_id"], r["hits"], r["held"]) for r in got} == {(7, 1, 18, 1.0), (7, 2, 18, 1.0)}


def test_arrival_cells_are_inserts_in_order(spark):
    rng = random.Random(12)
    rows = [(0, 0, f"b{rng.randrange(3)}", i) for i in range(160)]
    got = sketch.arrival_cells(spark.createDataFrame(rows, "node int, table_id int, bucket_key string, id long"), ["node", "table_id", "bucket_key"], 2, 8).collect()
    columns = {(r["id"], r["row"]): r["col"] for r in sketch.spread(spark.createDataFrame([(i,) for i in range(160)], "id long"), 2, 8).collect()}
    want = {}
    for key in ("b0", "b1", "b2"):
        one = sketch.VoteSketch(2, 8, lambda i, r: columns[i, r])
        for _, _, k, i in rows:
            if k == key:
                one.insert(i)
        want |= {(key, *place): cell for place, cell in one.cells.items()}
    assert {(r["bucket_key"], r["row"], r["col"]): (r["total"], r["cand"], r["votes"]) for r in got} == want


def test_tree_takes_a_shuffle_a_round_and_linear_one(spark):
    cells = spark.createDataFrame([(1, n, 0, 0, 2, n, 1) for n in range(8)], "query_id long, node int, row int, col int, total long, cand long, votes long")
    shuffles = {s: S.global_merge(cells, 8, s)._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") for s in ("tree", "array", "linear")}
    assert shuffles == {"tree": 3, "array": 1, "linear": 1}


def test_queries_from_another_table_keep_equal_ids(spark, small):
    from bucketvote.catalogue import asked, doc_sets

    rows = doc_sets(spark, small)
    q = asked(rows).limit(1)
    for strategy in ("tree", "exact"):
        first = S.search(rows, q, 1, 8, 3, 2, strategy, 2, 4096, exclude_self=False).where("rank = 1").first()
        assert first["id"] == first["query_id"]


def test_dense_pairs_in_blocks(spark, monkeypatch):
    from bucketvote.functions import similarity

    v = spark.createDataFrame([(i, [float(i % 7), 1.0]) for i in range(60)], "id long, v array<double>")
    few = {tuple(r) for r in similarity.dense_pairs(v, v.where("id < 30")).collect()}
    for name, value in (("FEW_QUERIES", 3), ("PART_ROWS", 11), ("BLOCK_QUERIES", 7)):
        monkeypatch.setattr(similarity, name, value)
    assert {tuple(r) for r in similarity.dense_pairs(v, v.where("id < 30")).collect()} == few and len(few) == 30 * 59
