"""Queries against DuckDB on the smallest tables, and properties of sketches, merges and plans."""

import random

import duckdb
import pytest
from pyspark.sql import functions as F

from bucketvote.every import QUERIES
from bucketvote.operators import search as S
from bucketvote.operators import sketch
from bucketvote.plans import theory
from bucketvote.sources.tables import TABLES

FEW = ["f01_doc_words", "h02_minhash", "h05_densify_per_bin", "h06_bucket_keys", "x03_union_law", "x05_sketch_cells", "x07_append_totals", "q04_tree_m7", "q05_linear_m7", "q09_search_tree", "q09_search_exact", "m02_cosine_top", "q12_near_duplicates", "th02_parameters", "c16_sketch_error"]


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    return con


def same(a, b):
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)

    def plain(x):
        return x[cols].astype(str).sort_values(cols).reset_index(drop=True)

    return plain(a).equals(plain(b))


@pytest.mark.parametrize("name", FEW)
def test_query_equals_sql(spark, small, duck, name):
    q = QUERIES[name]
    assert same(q.run(spark, small).toPandas(), duck.execute(q.sql).df())


def test_two_nodes_tree_is_linear(spark, small):
    assert same(QUERIES["q04_tree_m2"].run(spark, small).toPandas(), QUERIES["q05_linear_m2"].run(spark, small).toPandas())


def test_reference_sketch_bounds():
    rng = random.Random(3)
    for _ in range(300):
        s = sketch.VoteSketch(2, 4, lambda i, r: (i * (7 + 4 * r) + r) % 4)
        true = {}
        for _ in range(rng.randrange(1, 60)):
            i = rng.randrange(9)
            s.insert(i)
            true[i] = true.get(i, 0) + 1
        for (r, c), (total, cand, votes) in s.cells.items():
            assert votes <= true[cand] and true[cand] - (total - votes) / 2 <= votes
            for i, f in true.items():
                if s.columns(i, r) == c:
                    assert f <= total
                    if i != cand:
                        assert f <= (total - votes) / 2


def test_merge_pair_and_equal_candidates(spark):
    cols = "query_id long, node int, row int, col int, total long, cand long, votes long"
    apart = spark.createDataFrame([(1, 0, 0, 0, 5, 10, 3), (1, 1, 0, 0, 4, 20, 2)], cols)
    alike = spark.createDataFrame([(1, 0, 0, 0, 5, 10, 3), (1, 1, 0, 0, 4, 10, 2)], cols)
    for merge in (lambda c: sketch.merge_cells(c, ["query_id"]), lambda c: sketch.fold_cells(c, ["query_id"]), lambda c: S.global_merge(c, 2, "tree")):
        assert tuple(merge(apart).select("total", "cand", "votes").first()) == (9, 10, 1)
        assert tuple(merge(alike).select("total", "cand", "votes").first()) == (9, 10, 5)


def test_wide_sketch_equals_exact(spark, small):
    from bucketvote.catalogue import asked, doc_sets

    rows = doc_sets(spark, small)
    q = asked(rows, 20)
    tree = S.search(rows, q, 2, 12, 1, 3, "tree", 3, 1 << 20).select("query_id", "id").toPandas()
    exact = S.search(rows, q, 2, 12, 1, 3, "exact").select("query_id", "id").toPandas()
    assert same(tree, exact)


def test_search_reads_no_vectors_for_ranking(spark, small):
    from bucketvote.catalogue import qkeys

    keys, index = qkeys(spark, small), spark.createDataFrame([(0, "1-2", 0, 0, 1, 1, 7, 1)], "table_id int, bucket_key string, node int, row int, col int, total long, cand long, votes long")
    plan = S.local_merge(keys, index, queries=100, tables=12)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "CartesianProduct" not in plan


def test_weak_instance_and_sizes(spark):
    rows = {(r["n"], r["p1"]): r["strong"] for r in theory.choose_parameters(spark.range(1000).withColumn("o_orderpriority", F.lit("1-URGENT"))).collect()}
    assert rows[1000, 0.8] and not rows[1000, 0.7]
    assert S.tree_rounds(7) == 3 and S.tree_rounds(1) == 0 and theory.size_sketch(800, 4) == 400


def test_empty_and_wordless_texts(spark):
    from bucketvote.functions.features import token_sets
    from bucketvote.functions.hashing import keys_of

    docs = spark.createDataFrame([(1, None), (2, ""), (3, "..."), (4, "one"), (5, "one")], "doc_id long, text string")
    keys = keys_of(token_sets(docs, "doc_id", "text"), 2, 4)
    assert {r["id"] for r in keys.collect()} == {4, 5}
    assert keys.groupBy("table_id", "bucket_key").agg(F.count("*").alias("n")).where("n <> 2").count() == 0
