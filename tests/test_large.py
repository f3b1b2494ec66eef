"""What failed on large tables: against DuckDB and brute force."""

import random
from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

from bucketvote.every import QUERIES
from bucketvote.operators import hits, pairs
from bucketvote.operators import search as S
from bucketvote.sources.tables import TABLES


def by_sql(folder, sql):
    con = duckdb.connect()
    for t in TABLES:
        try:
            con.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
        except duckdb.IOException:
            con.execute(f"create or replace view {t} as select * from '{folder}/{t}.parquet/*.parquet'") if (folder / f"{t}.parquet").is_dir() else None
    return sorted(con.execute(sql).fetchall())


def test_combined_top_is_exact_beyond_a_sketch(spark, tmp_path):
    """More ids than the built-in sketch tracks, nearly all of one count."""
    rows = spark.range(90_000).withColumn("n", F.when(F.col("id") < 3, F.lit(3)).otherwise(F.lit(2))).select("id", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("i"))
    rows.select(F.xxhash64("id", "i").alias("event_id"), F.col("id").alias("user_id"), F.lit("view").alias("event_type")).write.parquet(f"{tmp_path}/events.parquet")
    q = QUERIES["s12_combined_top_k"]
    assert sorted(map(tuple, q.run(spark, str(tmp_path)).collect())) == by_sql(tmp_path, q.sql)


SHINGLED = ("b01_brute_force", "m01_jaccard_top", "m02_weighted_cosine_top", "m04_distances", "q11_within", "q07_classic_lsh", "b04_or_only_lsh", "th04_sensitivity", "o27_arrow_function")


@pytest.mark.parametrize("name", SHINGLED)
def test_blocks_give_what_sql_gives_and_shuffle_no_pair(spark, tmp_path, monkeypatch, name):
    """Small blocks, steps and postings; copies, near copies, repeated words and a word in every text."""
    for what, value in (("BLOCK", 3), ("STEP", 7), ("POSTINGS", 50)):
        monkeypatch.setattr(pairs, what, value)
    rng = random.Random(3)
    texts = [" ".join(["the", *rng.choices([f"w{i}" for i in range(60)], k=rng.randrange(1, 60))]) for _ in range(60)]
    docs = [(i * 10, texts[rng.randrange(60)] + (" more" if i % 3 else "")) for i in range(150)] + [(7, None), (8, " !"), (9, "alone")]
    spark.createDataFrame(docs, "doc_id long, text string").coalesce(3).write.parquet(f"{tmp_path}/documents.parquet")
    q = QUERIES[name]
    made = q.run(spark, str(tmp_path))
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "explode" not in plan.lower()
    assert sorted(map(tuple, made.select(*sorted(made.columns)).collect())) == by_sql(tmp_path, f"SELECT {', '.join(chr(34) + c + chr(34) for c in sorted(made.columns))} FROM ({q.sql})")


MOVED = ["c14_hash_cost", "th01_curve", "th02_parameters", "th05_signal_to_noise", "th06_cost_model", "th07_dedup_limit", "th08_repetitions", "th09_sketch_size"]


@pytest.mark.parametrize("name", MOVED)
def test_closed_forms_read_a_table(spark, small, name):
    made = QUERIES[name].run(spark, small)
    assert "FileScan parquet" in made._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, made.select(*sorted(made.columns)).collect())) == by_sql(Path(small), f"SELECT {', '.join(sorted(made.columns))} FROM ({QUERIES[name].sql})")


def odd_documents(spark, folder):
    """Copies, near copies, a word in every text, texts without a word; and vectors."""
    rng = random.Random(5)
    texts = [" ".join(["the", *rng.choices([f"w{i}" for i in range(60)], k=rng.randrange(1, 60))]) for _ in range(50)]
    docs = [(i * 10, texts[rng.randrange(50)] + (" more" if i % 3 else "")) for i in range(150)] + [(7, None), (8, " !"), (9, "alone")]
    spark.createDataFrame(docs, "doc_id long, text string").coalesce(3).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(i, [rng.gauss(0, 1) for _ in range(64)]) for i in range(300)], "vec_id long, embedding array<float>").write.parquet(f"{folder}/embeddings.parquet")


@pytest.mark.parametrize("name", ["w10_reservoirs", "w15_parameter_sweep", "w13_hash_families", "w08_large_batch"])
def test_keys_meet_in_postings_and_no_join(spark, tmp_path, monkeypatch, name):
    def no_join(*a, **b):
        raise AssertionError("a row for each pair that shares a bucket")

    odd_documents(spark, tmp_path)
    for where in ("exact_counts", "with_similarity", "probe"):
        monkeypatch.setattr(S, where, no_join)
    monkeypatch.setattr(hits, "POSTINGS", 100)
    q = QUERIES[name]
    made = q.run(spark, str(tmp_path))
    assert sorted(map(tuple, made.select(*sorted(made.columns)).collect())) == by_sql(tmp_path, f"SELECT {', '.join(chr(34) + c + chr(34) for c in sorted(made.columns))} FROM ({q.sql})")


def test_builtin_lsh_meets_in_blocks_and_keeps_the_nearest(spark, tmp_path):
    from pyspark.ml.feature import MinHashLSH

    from bucketvote.catalogue import doc_sets, top_by
    from bucketvote.functions import features
    from bucketvote.sources.shared import stored

    odd_documents(spark, tmp_path)
    v = features.to_ml_vector(stored(doc_sets(spark, str(tmp_path)), "sets")).select("id", "features")
    model = MinHashLSH(inputCol="features", outputCol="h", numHashTables=8, seed=1).fit(v)
    met = model.approxSimilarityJoin(v.where("id % 100 = 0"), v, 0.95, "distance").selectExpr("datasetA.id query_id", "datasetB.id id", "1 - distance similarity").where("query_id <> id")
    made = QUERIES["b03_builtin_lsh_join"].run(spark, str(tmp_path))
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "Join" not in plan
    assert sorted(map(tuple, made.collect())) == sorted(map(tuple, top_by(met).collect()))
    single = {(r["query_id"], r["id"], round(r["similarity"], 6)) for r in QUERIES["b02_builtin_lsh_single"].run(spark, str(tmp_path)).collect()}
    every = model.approxSimilarityJoin(v.where("id % 100 = 0"), v, 1.1, "distance").selectExpr("datasetA.id query_id", "datasetB.id id", "1 - distance similarity").where("query_id <> id")
    assert single == {(r["query_id"], r["id"], r["similarity"]) for r in top_by(every).collect()}


def test_exact_index_of_a_trial_is_not_written_for_each_node_count(spark, small, monkeypatch):
    from bucketvote.catalogue import asked, doc_sets
    from bucketvote.plans import workloads

    rows = doc_sets(spark, small)
    trial, written = workloads.Trial(rows, asked(rows), 2, 6), []
    monkeypatch.setattr(workloads, "stored", lambda df, name: written.append(name) or df)
    index = trial.index(5, strategy="exact")
    assert not written and index.columns == ["node", "table_id", "bucket_key", "id"]
    got = trial.search(index, 5, 5, "exact").collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, S.search(rows, asked(rows), 2, 6, 5, 5, "exact").collect()))


def families(spark, folder):
    """A family of 100 differing copies, a smaller one, exact copies, short texts, texts without a word."""
    rng = random.Random(11)
    docs = []
    for size, length in ((100, 150), (12, 300), (30, 7)):
        base = [f"w{rng.randrange(500)}" for _ in range(length)]
        for _ in range(size):
            own = list(base)
            for _ in range(rng.randrange(3)):
                own[rng.randrange(length)] = f"x{rng.randrange(9)}"
            docs.append(" ".join(own) + rng.choice(["", " and more", "!"]))
    docs += [docs[0], docs[5], "one", "ONE", "two words", "", " !", None, *(" ".join(rng.choices(["a", "b", "c"], k=9)) for _ in range(40))]
    rng.shuffle(docs)
    spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string").repartition(3).write.parquet(f"{folder}/documents.parquet")


def test_links_meet_inside_tasks(spark, tmp_path, monkeypatch):
    from bucketvote.catalogue import WORDS, doc_sets
    from bucketvote.operators import duplicates

    def no_join(*a, **b):
        raise AssertionError("a row with both token sets for each pair")

    families(spark, tmp_path)
    monkeypatch.setattr(duplicates, "_verified", no_join)
    monkeypatch.setattr(hits, "POSTINGS", 500)
    for what, value in (("CHUNK", 7), ("BLOCK", 50), ("PAIRS", 300), ("HELD", 2000)):
        monkeypatch.setattr(duplicates, what, value, raising=False)
    q = QUERIES["q12_near_duplicates"]
    made = q.run(spark, str(tmp_path))
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan
    want = by_sql(tmp_path, f"SELECT id_a, id_b, hits, jaccard FROM ({q.sql})")
    assert len(want) > 1000 and sorted(map(tuple, made.select("id_a", "id_b", "hits", "jaccard").collect())) == want
    sets = doc_sets(spark, str(tmp_path), "shingle", WORDS)
    assert sorted(map(tuple, duplicates.links(sets, 2, 16).collect())) == want


@pytest.mark.parametrize("part", [400_000, 60])
def test_node_index_is_the_sketch_index(spark, small, monkeypatch, part):
    """Made by the task of each node, whole or in parts: the cells of the aggregation over all ids and tables."""
    from bucketvote.operators import cells
    from bucketvote.plans import workloads
    from bucketvote.workload_queries import line_sets

    monkeypatch.setattr(cells, "PART", part)
    monkeypatch.setattr(cells, "BATCH", 100)
    rows = line_sets(spark, small).limit(700).localCheckpoint()
    want = S.build_sketch_index(S.build_bucket_index(rows, 4, 6, 3), 2, 64)
    want = want.withColumn("bucket_key", F.concat_ws("", F.transform(F.split("bucket_key", "-"), lambda v: F.lpad(F.hex(v.cast("long")), 16, "0"))))
    made = cells.node_index(rows, 4, 6, 3, 2, 64)
    assert ("Aggregate" in made._jdf.queryExecution().executedPlan().toString()) == (part == 60)
    assert sorted(map(tuple, made.withColumn("bucket_key", F.hex("bucket_key")).collect())) == sorted(map(tuple, want.select(*made.columns).collect()))

    def no_rows(*a, **b):
        raise AssertionError("a row for each id, table and sketch row")

    monkeypatch.setattr(S, "build_sketch_index", no_rows)
    got = workloads.index_scaling(spark, {"lineitem": (rows, 4, 6)}, (2, 3), 2, 64).collect()
    assert sorted((r["family"], r["nodes"]) for r in got) == [("lineitem", 2), ("lineitem", 3)] and all(r["seconds"] > 0 for r in got)


@pytest.mark.parametrize("table", ["lineitem", "documents"])
def test_quality_in_tasks_is_that_of_the_plans(spark, small, monkeypatch, table):
    from bucketvote.catalogue import asked, doc_sets
    from bucketvote.plans import workloads
    from bucketvote.workload_queries import line_sets

    rows = (line_sets(spark, small).where("id % 100 = 0 or id % 5 = 1") if table == "lineitem" else doc_sets(spark, small)).localCheckpoint()
    k, tables, nodes, ks = 2 if table == "lineitem" else 1, 6, (2, 3, 7), (1, 20)
    want = workloads.quality_over_nodes(workloads.Trial(rows, asked(rows), k, tables), nodes, ks, 2, 32).collect()

    def no_plan(*a, **b):
        raise AssertionError("a row for each cell of a query")

    monkeypatch.setattr(S, "search_index", no_plan)
    monkeypatch.setattr(S, "build_sketch_index", no_plan)
    made = workloads.quality_in_tasks(rows, asked(rows), k, tables, nodes, ks, 2, 32)
    columns = sorted(made.columns)
    assert sorted(columns) == sorted(want[0].asDict()) and len(want) == 18
    assert sorted(tuple(r[c] for c in columns) for r in made.collect()) == sorted(tuple(r[c] for c in columns) for r in want)
    monkeypatch.setattr(workloads, "quality_over_nodes", no_plan)
    assert QUERIES["w05_quality_clicks"].run(spark, small).count() == 48


def test_node_of_over_a_million_rows_is_built_without_a_shuffle_of_cells(spark, small):
    from bucketvote.operators import cells
    from bucketvote.workload_queries import line_sets

    plan = cells.node_index(line_sets(spark, small), 4, 16, 2, 2, 1024, 3_600_000)._jdf.queryExecution().executedPlan().toString()
    # the first aggregation is that of line_sets
    assert "MapInArrow" in plan and "Aggregate" not in plan[: plan.index("MapInArrow")]


def test_compact_hashes_give_the_keys_and_salts(monkeypatch):
    import numpy as np
    import pyarrow as pa

    rng = random.Random(2)
    ids = [0, 9, 10, 99, 100, 10**17 + 3, 2**63 - 1, *rng.sample(range(1 << 56), 500)]
    for ends in ((), ("/0", "/1/15")):
        assert (hits.id_numbers(np.array(ids), *ends) == [hits.numbers(f"{i}{e}" for i in ids) for e in (ends or ("",))]).all()
    rows = [(i, [f"w{rng.randrange(9)}" for _ in range(rng.randrange(5))]) for i in ids]
    batch = pa.RecordBatch.from_arrays([pa.array([i for i, _ in rows]), pa.array([t for _, t in rows], pa.list_(pa.string()))], names=["id", "tokens"])
    known, (want,) = hits.batch_keys(batch, [hits.Way(4, 3)])
    held = hits.Hashed.of([hits.Hashed.part(batch.slice(a, 100)) for a in range(0, len(ids), 100)])
    assert (held.ids == known).all()
    for mix in (hits._ODD, (0, 0)):  # the second makes all keys one mix
        monkeypatch.setattr(hits, "_ODD", mix)
        for t in range(3):
            sig = held.bins(12, 4 * t, 4 * t + 4, step=64)
            assert (np.ascontiguousarray(sig.T, ">i8").view("S32").ravel() == want[t]).all()
            code, first = hits.codes(sig)
            assert (first[code] == np.unique(want[t], return_index=True)[1][np.unique(want[t], return_inverse=True)[1]]).all()


@pytest.mark.parametrize("table", ["lineitem", "documents"])
def test_stored_whole_index_is_searched_inside_tasks(spark, small, monkeypatch, table):
    """The answers of the plans, from an index of all buckets that is freed after use."""
    from bucketvote.catalogue import asked, doc_sets
    from bucketvote.operators import votes
    from bucketvote.plans import workloads
    from bucketvote.sources.shared import opened
    from bucketvote.workload_queries import line_sets

    rows = (line_sets(spark, small).where("id % 100 = 0 or id % 5 = 1") if table == "lineitem" else doc_sets(spark, small)).localCheckpoint()
    k, tables = (4, 6) if table == "lineitem" else (1, 6)
    monkeypatch.setattr(votes, "PLACES", 3 * 7 * 2 * 64)
    monkeypatch.setattr(votes, "ASKED", 10)
    trial = workloads.Batch(rows, asked(rows), k, tables, 2, 64)
    for m in (1, 7):
        want = {x: sorted((r["query_id"], r["rank"], r["id"]) for r in S.search(rows, asked(rows), k, tables, 20, m, x, 2, 64).collect()) for x in ("tree", "linear", "exact")}
        index = trial.index(m)
        with monkeypatch.context() as no:
            no.setattr(S, "probe", None)
            for strategy, answers in want.items():
                got = trial.search(index, 20, m, strategy)
                assert answers and sorted(map(tuple, got.collect())) == answers
        trial.free(index)
        fs, inside = opened(index)
        assert fs.get_file_info(inside).type.name == "NotFound"


def test_timings_run_without_a_join_of_cells(spark, tmp_path, monkeypatch):
    from bucketvote.catalogue import asked, doc_sets
    from bucketvote.plans import workloads
    from bucketvote.workload_queries import against_builtin, text_batch

    odd_documents(spark, tmp_path)
    rows = doc_sets(spark, str(tmp_path))
    want = workloads.Trial(rows, asked(rows), 1, 12)
    quality = want.quality(S.search(rows, asked(rows), 1, 12, 128, 3, "tree", 2, 1024), (128,)).first()
    monkeypatch.setattr(S, "probe", None)
    monkeypatch.setattr(S, "build_sketch_index", None)
    made = against_builtin(spark, str(tmp_path), (3, 4)).collect()
    assert [(r["method"], r["nodes"]) for r in made] == [("sketch tree", 3), ("sketch tree", 4), ("built-in join", 1), ("built-in single", 1)]
    assert (made[0]["s_at_k"], made[0]["coverage"]) == (quality["s_at_k"], quality["coverage"]) and all(r["seconds"] > 0 for r in made)
    timed = workloads.query_scaling(spark, {"documents": lambda: text_batch(spark, str(tmp_path))}, (2, 3)).collect()
    assert len(timed) == 6 and all(r["ms_per_query"] > 0 for r in timed)
