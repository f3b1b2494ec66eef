"""Experiments and the remaining measures, searches and baselines as queries."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .catalogue import B, CLASSES, COS, DEPTH, JACCARD, K, NODES, TABLES, WIDTH, WORDS, asked, asked_build, buckets, cells, doc_sets, ml_join, ml_single, near_classes, qkeys, shingles_sql, signs_sql, top_by
from .functions import features, hashing, similarity
from .operators import hits, pairs
from .operators import search as S
from .oracle import LINE_SETS, Build, num, union_all
from .plans import measures, theory, workloads
from .registry import add
from .sources.shared import shared_folder, stored
from .sources.tables import load, load_index, save_index


def line_sets(s, d):
    return features.line_rows(load(s, d, "lineitem")).dropDuplicates(["id"])


def text_trial(s, d, k=1, tables=12):
    rows = doc_sets(s, d)
    return workloads.Trial(rows, asked(rows), k, tables)


def text_batch(s, d, k=1, tables=12):
    rows = doc_sets(s, d)
    return workloads.Batch(rows, asked(rows), k, tables)


def click_batch(s, d, k=4, tables=16):
    rows = stored(line_sets(s, d), "lines")
    return workloads.Batch(rows, asked(rows), k, tables)


# searches and measures
add("q11_within", asked_build().pairs().select(f"SELECT query_id, id, round(1 - {COS}, 6) distance FROM sim_rows WHERE round(1 - {COS}, 6) <= 0.7"))(lambda s, d: S.within(doc_sets(s, d), asked(doc_sets(s, d)), 0.7))
add("q11_bounded", asked_build().pairs().select(f"SELECT query_id, count(*) near, count(*) <= 3 bounded FROM sim_rows WHERE round(1 - {COS}, 6) <= 0.7 GROUP BY query_id"))(lambda s, d: S.is_k_bounded(doc_sets(s, d), asked(doc_sets(s, d)), 0.7, 3))
add("q10_near_neighbor", B().queries().counts().pairs().add("first_hit", "SELECT query_id, id FROM counts WHERE query_id <> id QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) = 1").select(f"SELECT s.query_id, s.id, round(1 - {COS}, 6) distance FROM first_hit f JOIN sim_rows s ON s.query_id = f.query_id AND s.id = f.id WHERE round(1 - {COS}, 6) <= 0.4 * 2"))(
    lambda s, d: S.near_neighbor(S.search(doc_sets(s, d), asked(doc_sets(s, d)), K, TABLES, 1, NODES, "exact"), doc_sets(s, d), asked(doc_sets(s, d)), 0.4, 2.0)
)


def online(s, d):
    path = shared_folder(s, "index")
    made = cells(s, d)
    save_index(made, path)
    one = S.hash_queries(asked(doc_sets(s, d), 1), K, TABLES)
    return S.search_one(one, load_index(s, path, made.schema), 10, NODES, "tree", DEPTH, WIDTH)


add("q13_search_one", Build().buckets(K, TABLES, NODES).cells(DEPTH, WIDTH).queries(1).local().tree(NODES).top(10, DEPTH, WIDTH).select('SELECT query_id, "rank", id, votes, upper FROM answers'))(online)
SKEW = """SELECT table_id, count(*) buckets, max(n) largest, round(quantile_cont(n, 0.99), 6) p99, round(2 * sum(i * n) / (count(*) * CAST(sum(n) AS DOUBLE)) - (count(*) + 1) / CAST(count(*) AS DOUBLE), 6) gini
  FROM (SELECT table_id, n, row_number() OVER (PARTITION BY table_id ORDER BY n) i FROM (SELECT table_id, bucket_key, count(*) n FROM buckets GROUP BY ALL)) GROUP BY table_id"""
add("c12_skew", B().select(SKEW))(lambda s, d: measures.skew_report(buckets(s, d)))
add("w10_bucket_skew_lines", Build(LINE_SETS).buckets(4, 16, NODES).select(SKEW))(lambda s, d: measures.skew_report(S.build_bucket_index(line_sets(s, d), 4, 16, NODES)))
add("c14_hash_cost", Build().select("SELECT k, l, k * l per_minhash, 1 per_one_permutation, CAST(n * k * l AS BIGINT) all_minhash, n all_one_permutation FROM (SELECT count(*) n FROM sets), (VALUES (4, 24), (4, 16), (4, 32), (2, 32), (1, 32)) t(k, l)"))(lambda s, d: theory.hash_cost(doc_sets(s, d)))
add("th09_sketch_size", "SELECT load_ids, hits, suppliers, CAST(ceil(2 * load_ids / CAST(hits AS DOUBLE)) AS INTEGER) width FROM (SELECT load_ids, count(*) suppliers FROM (SELECT l_suppkey, count(*) load_ids FROM lineitem GROUP BY 1) GROUP BY 1), (VALUES (4), (12)) t(hits)")(lambda s, d: theory.sketch_sizes(load(s, d, "lineitem")))


def sensitivity(s, d):
    rows = hashing.beside_tokens(doc_sets(s, d), lambda sets: hashing.minhash(sets, 64))
    return pairs.agreement(rows, asked(rows), 0.5, 0.2)


add("th04_sensitivity", Build().asked().minhash(64).pairs().agreement().select(f"SELECT round(avg(rate) FILTER ({JACCARD} >= 0.5), 6) p1, round(avg(rate) FILTER ({JACCARD} <= 0.2), 6) p2 FROM agreed"))(sensitivity)


# baselines
def dense(s, d):
    return load(s, d, "embeddings").where("embedding is not null").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))


def dense_truth(v, q, k):
    return top_by(similarity.dense_pairs(v, q), k)


def projected(s, d, bits=4, tables=16):
    """Vectors, queries, and the hits of projection keys."""
    v = stored(dense(s, d), "vectors")
    q = stored(asked(v), "queries")
    keys = hashing.bucket_keys(hashing.signed_projection(v, "id", "v", bits * tables, 64), bits, tables)
    mine = keys.join(q.select("id"), "id", "left_semi").withColumnRenamed("id", "query_id")
    return v, q, S.exact_counts(mine, keys)


def with_cosine(met, v, q):
    both = met.join(v, "id").join(q.select(F.col("id").alias("query_id"), F.col("v").alias("q")), "query_id")
    return both.withColumn("similarity", similarity.cosine_dense(F.col("q"), F.col("v"))).drop("q", "v")


def projection(s, d, bits=4, tables=16, k=5):
    """Recall of projection keys with exact distances among what they meet."""
    v, q, met = projected(s, d, bits, tables)
    found = top_by(with_cosine(met.where("query_id <> id"), v, q), k)
    return measures.recall_at_k(found, dense_truth(v, q, k), k)


def projected_sql(bits=4, tables=16):
    """Common table expressions `hit` (query_id, id, hits) and `near` (query_id, id, c) of query rows with all others."""
    return f"""WITH signs AS ({signs_sql(bits * tables, 64)}), keys AS (SELECT id, bin // {bits} table_id, string_agg(CAST(value AS VARCHAR), '-' ORDER BY bin) bucket_key FROM signs GROUP BY ALL),
 vec AS (SELECT vec_id id, CAST(embedding AS DOUBLE[]) v FROM embeddings WHERE embedding IS NOT NULL),
 hit AS (SELECT a.id query_id, b.id, count(*) hits FROM keys a JOIN keys b USING (table_id, bucket_key) WHERE a.id % 100 = 0 AND a.id <> b.id GROUP BY ALL),
 near AS (SELECT a.id query_id, b.id, list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v) * list_dot_product(b.v, b.v)) c FROM vec a JOIN vec b ON a.id % 100 = 0 AND a.id <> b.id)"""


add("b09_projection_lsh", f"""{projected_sql()}, truth AS (SELECT query_id, id FROM near QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(c, 9) DESC, id) <= 5),
 got AS (SELECT query_id, id FROM near SEMI JOIN hit USING (query_id, id) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(c, 9) DESC, id) <= 5)
 SELECT CAST(5 AS INTEGER) k, found, wanted, round(found / CAST(wanted AS DOUBLE), 6) recall FROM (SELECT count(*) found FROM truth SEMI JOIN got USING (query_id, id)), (SELECT count(*) wanted FROM truth)""")(projection)


def coarse(s, d, lists=16, probes=10, k=5, fit_rows=20_000):
    """Recall of a coarse quantiser fitted on at most fit_rows rows of least hash; every row is indexed."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = dense(s, d).withColumn("features", array_to_vector(F.col("v").cast("array<double>")))
    model = KMeans(k=lists, seed=1, maxIter=10).fit(asked(v, fit_rows))
    placed = stored(model.transform(v).select("id", "v", F.col("prediction").alias("list")), "lists")
    centres = s.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(model.clusterCenters())], "list int, c array<double>")
    q = stored(asked(placed).select("id", "v"), "queries")
    gap = F.aggregate(F.zip_with("v", "c", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda t, x: t + x)
    # the centres are `lists` rows by definition
    near = q.join(F.broadcast(centres)).withColumn("r", F.row_number().over(Window.partitionBy("id").orderBy(gap, "list"))).where(F.col("r") <= probes)
    both = placed.join(near.select(F.col("id").alias("query_id"), F.col("v").alias("q"), "list"), "list").where("query_id <> id")
    found = top_by(both.select("query_id", "id", similarity.cosine_dense(F.col("q"), F.col("v")).alias("similarity")), k)
    return measures.recall_at_k(found, dense_truth(placed, q, k), k)


add("b11_coarse_quantiser")(coarse)


# workloads
def against_builtin(s, d, nodes=(3, 4, 5, 6, 7, 8), k=128, single=5):
    """Time and mean cosine of the top k: batches of queries from a stored index, the built-in hashes met in blocks for all queries (built-in join), and for the first `single` (built-in single)."""
    trial, times, answers = text_batch(s, d), [], []

    def report(name, m, n, run):
        times.append((name, m, n, measures.timed(run)))
        answers.append(stored(run.select(F.lit(len(answers)).alias("run"), "query_id", F.col("rank").cast("int").alias("rank"), "id"), "answers"))

    for m in nodes:
        index = trial.index(m)
        run = trial.search(index, k, m, "tree")
        measures.timed(run)
        report("sketch tree", m, trial.n, run)
        trial.free(index)
    report("built-in join", 1, trial.n, ml_join(s, d, k))
    few = min(single, trial.n)
    near = ml_single(s, d, few, k)
    times.append(("built-in single", 1, few, measures.timed(near)))
    answers.append(stored(top_by(near, k).select(F.lit(len(answers)).alias("run"), "query_id", F.col("rank").cast("int").alias("rank"), "id"), "answers"))
    # each pair of a query and an answer is compared once, however many searches give it
    found = workloads.together(answers)
    scored = found.join(hits.graded_pairs(found.select("query_id", "id").distinct(), trial.rows, trial.queries), ["query_id", "id"])
    per = scored.groupBy("run", "query_id").agg(F.avg("similarity").alias("s"), F.count("*").alias("n"))
    got = {r["run"]: r for r in per.groupBy("run").agg(F.round(F.avg("s"), 6).alias("s"), F.sum("n").alias("n")).collect()}
    rows = [(name, m, n, round(seconds, 3), round(1000 * seconds / max(1, n), 3), got[i]["s"] if i in got else None, round(got[i]["n"] / (k * trial.n), 6) if i in got else 0.0) for i, (name, m, n, seconds) in enumerate(times)]
    return s.createDataFrame(rows, "method string, nodes int, queries int, seconds double, ms_per_query double, s_at_k double, coverage double")


add("w02_against_builtin")(against_builtin)
add("w03_index_scaling")(lambda s, d: workloads.index_scaling(s, {"lineitem": (line_sets(s, d), 4, 16), "documents": (doc_sets(s, d), 4, 24)}))
add("w04_query_scaling")(lambda s, d: workloads.query_scaling(s, {"lineitem": lambda: click_batch(s, d), "documents": lambda: text_batch(s, d, 4, 24)}))


def quality_clicks(s, d):
    rows = stored(line_sets(s, d), "lines")
    return workloads.quality_in_tasks(rows, asked(rows), 4, 16)


add("w05_quality_clicks")(quality_clicks)
#: K and L of the text experiment, and of short keys that cover more.
TEXT = ((4, 24), (1, 12))


def quality_text(s, d):
    out = [workloads.quality_over_nodes(text_trial(s, d, k, t)).select(F.lit(k).alias("per_key"), F.lit(t).alias("tables"), "strategy", "nodes", "k", "s_at_k", "coverage", "queries", "ideal", "gap") for k, t in TEXT]
    return workloads.together(out)


def quality_text_sql(k, t, ks=(1, 64), depth=2, width=1024):
    parts = []
    for m in workloads.EVERY_NODES:
        for strategy in ("tree", "linear"):
            b = getattr(Build().buckets(k, t, m).cells(depth, width).queries().local(), strategy)(m).top(max(ks), depth, width)
            b.add("placed_ids", 'SELECT query_id, "rank" rk, id FROM answers').graded(ks=ks)
            parts.append(b.select(f"SELECT '{strategy}' strategy, CAST({m} AS INTEGER) nodes, * FROM graded"))
    nodes = ", ".join(f"({m})" for m in workloads.EVERY_NODES)
    # exact counts are the same on any number of nodes
    parts.append(Build().buckets(k, t, 1).queries().counts().hits(max(ks)).graded(ks=ks).select(f"SELECT 'exact' strategy, CAST(m AS INTEGER) nodes, g.* FROM graded g, (VALUES {nodes}) t(m)"))
    best = asked_build().pairs().add("placed_ids", f"SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY round({COS}, 9) DESC, id) AS rk, id FROM sim_rows QUALIFY rk <= {max(ks)}")
    ideal = best.graded(ks=ks).select("SELECT k, s_at_k AS ideal FROM graded")
    return f"SELECT CAST({k} AS INTEGER) per_key, CAST({t} AS INTEGER) AS tables, a.*, ideal, round(ideal - s_at_k, 6) gap FROM ({union_all(parts)}) a JOIN ({ideal}) i ON a.k = i.k"


add("w06_quality_text", union_all([quality_text_sql(k, t) for k, t in TEXT]))(quality_text)
add("w07_large_scale")(lambda s, d: workloads.large_scale(s, line_sets(s, d), asked(line_sets(s, d))))


def whole_batch(s, d):
    """Every document asks at once: keys meet in posting lists inside tasks."""
    best = hits.tops_of_many(doc_sets(s, d), doc_sets(s, d), [hits.Way(K, TABLES)], 10).where("rank > 0")
    return best.agg(F.count("*").alias("answers"), F.count_distinct("query_id").alias("answered"), F.sum("hits").alias("hits"))


BATCH = B().add("c", "SELECT a.id query_id, b.id, count(*) hits FROM buckets a JOIN buckets b USING (table_id, bucket_key) WHERE a.id <> b.id GROUP BY ALL").add("t", "SELECT * FROM c QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) <= 10")
add("w08_large_batch", BATCH.select("SELECT count(*) answers, count(DISTINCT query_id) answered, CAST(sum(hits) AS BIGINT) hits FROM t"))(whole_batch)


def whole_batch_sketch(s, d):
    """Every document asks at once, answered by sketches and the tree."""
    found = S.search(doc_sets(s, d), doc_sets(s, d), K, TABLES, 10, NODES, "tree", DEPTH, WIDTH)
    return found.agg(F.count("*").alias("answers"), F.count_distinct("query_id").alias("answered"), F.sum("votes").alias("votes"), F.sum("upper").alias("upper"))


EVERY = B().cells(DEPTH, WIDTH).add("qkeys", "SELECT id query_id, table_id, bucket_key FROM keys").local().tree(NODES).top(10, DEPTH, WIDTH)
add("w08_sketch_batch", EVERY.select("SELECT count(*) answers, count(DISTINCT query_id) answered, CAST(sum(votes) AS BIGINT) votes, CAST(sum(upper) AS BIGINT) AS upper FROM answers"))(whole_batch_sketch)


def class_report(s, d):
    """Classes of two or more documents: how many, their documents, and how many hold one language only."""
    c = near_classes(s, d).join(load(s, d, "documents").select(F.col("doc_id").alias("id"), "lang"), "id")
    per = c.groupBy("class_id").agg(F.count("*").alias("n"), F.count_distinct("lang").alias("langs")).where("n > 1")
    return per.agg(F.count("*").alias("classes"), F.coalesce(F.sum("n"), F.lit(0)).alias("documents"), F.sum((F.col("langs") <= 1).cast("long")).alias("one_language"))


add("w09_near_duplicates", f"SELECT count(*) classes, CAST(sum(n) AS BIGINT) documents, count(*) FILTER (langs <= 1) one_language FROM (SELECT class_id, count(*) n, count(DISTINCT lang) langs FROM ({CLASSES}) c JOIN documents ON doc_id = id GROUP BY class_id) WHERE n > 1")(class_report)


def duplicate_recall(s, d, least=0.8):
    """Distances computed, links found and true links of the query rows: every pair of `least` or more, by a join on all shingles."""
    rows = doc_sets(s, d, "shingle", WORDS)
    q = asked(rows)
    met = S.with_similarity(S.exact_counts(S.hash_queries(q, 2, 16), S.build_bucket_index(rows, 2, 16)).where("query_id <> id"), rows, q, "jaccard")
    got = met.agg(F.count("*").alias("distances"), F.count_if(F.col("similarity") >= least).alias("links"))
    true = similarity.shared_tokens(rows, q, "jaccard").agg(F.count_if(F.col("similarity") >= least).alias("true_links"))
    share = {"precision": F.expr("round(links / nullif(distances, 0), 6)"), "recall": F.expr("round(links / nullif(true_links, 0), 6)")}
    return got.crossJoin(true).withColumns(share)  # a row each


add("w09_recall", Build(shingles_sql(WORDS)).buckets(2, 16, 1).queries().counts().pairs().add("tried", f"SELECT count(*) distances, count(*) FILTER ({JACCARD} >= 0.8) links FROM counts c LEFT JOIN sim_rows s ON s.query_id = c.query_id AND s.id = c.id WHERE c.query_id <> c.id").add("truth", f"SELECT count(*) FILTER ({JACCARD} >= 0.8) true_links FROM sim_rows").select("SELECT *, round(links / CAST(nullif(distances, 0) AS DOUBLE), 6) AS precision, round(links / CAST(nullif(true_links, 0) AS DOUBLE), 6) recall FROM tried, truth"))(duplicate_recall)
CAPS, SWEPT = (8, 32, 128), (8, 16, 24, 32)


def reservoirs_sql(set_sql, k, tables):
    parts = []
    for t in tables:
        for cap in (*CAPS, 0):
            b = Build(set_sql).buckets(k, t, NODES)
            if cap:
                b.add("kept", f"SELECT * FROM buckets QUALIFY row_number() OVER (PARTITION BY node, table_id, bucket_key ORDER BY {num("concat_ws('/', id, table_id)")}, id) <= {cap}")
            b.queries().counts("kept" if cap else "buckets").hits(10).graded()
            parts.append(b.select(f"SELECT CAST({t} AS INTEGER) AS tables, CAST({cap} AS INTEGER) cap, s_at_k, coverage FROM graded"))
    return union_all(parts)


add("w10_reservoirs", reservoirs_sql(None, 1, SWEPT))(lambda s, d: workloads.reservoirs(doc_sets(s, d), asked(doc_sets(s, d)), 1, SWEPT, CAPS))
add("w10_reservoirs_lines")(lambda s, d: workloads.reservoirs(line_sets(s, d), asked(line_sets(s, d)), 4, SWEPT, CAPS))


def traffic(s, d, m=16):
    local = stored(S.local_merge(qkeys(s, d), cells(s, d, m)), "local")
    per = S.probe(qkeys(s, d), buckets(s, d, m)).groupBy("query_id", "node", "id").agg(F.count("*").alias("hits"))
    return measures.communication_volume(local, per, m)


ROUNDS = " + ".join(f'(SELECT count(*) FROM (SELECT DISTINCT query_id, node // {1 << i} n, "row", col FROM local_cells) WHERE n % 2 = 1)' for i in range(4))
add("w11_communication", B(16).cells(DEPTH, WIDTH).queries().local().add("per", "SELECT DISTINCT q.query_id, node, b.id FROM qkeys q JOIN buckets b USING (table_id, bucket_key)").select(f"SELECT 'linear' strategy, count(*) n FROM local_cells WHERE node > 0 UNION ALL SELECT 'exact', count(*) FROM per WHERE node > 0 UNION ALL SELECT 'tree', {ROUNDS}"))(traffic)
DEPTHS, WIDTHS = (1, 2, 3, 4), (64, 128, 256, 512, 1024, 2048, 4096)


def sketch_size_sql(depth, width):
    b = Build().buckets(1, 12, NODES).cells(depth, width).queries().local().tree(NODES).top(10, depth, width).counts()
    b.add("placed_ids", 'SELECT query_id, "rank" rk, id FROM answers').graded()
    b.add("err", "SELECT round(avg(a.upper - coalesce(hits, 0)), 6) mean_over, round(avg(coalesce(hits, 0) - votes), 6) mean_under FROM answers a LEFT JOIN counts c ON c.query_id = a.query_id AND c.id = a.id")
    return b.select(f"SELECT CAST({depth} AS INTEGER) AS depth, CAST({width} AS INTEGER) width, s_at_k, coverage, mean_over, mean_under FROM graded, err")


add("w12_sketch_size", union_all([sketch_size_sql(x, w) for x in DEPTHS for w in WIDTHS]))(lambda s, d: workloads.sketch_sizes(text_trial(s, d), DEPTHS, WIDTHS, 10, NODES))


def family_quality(s, d, answers=10):
    """Set families on documents by exact counting, and projections on embeddings; quality is the mean cosine of the first answers."""
    v = dense(s, d)
    signs = hashing.signed_projection(v, "id", "v", 64, 64)
    q, met = asked(v), stored(hits.tops(signs, asked(signs), [hits.Way(4, 16)], answers), "answers")
    first = with_cosine(met.where("rank > 0").select("query_id", "id"), v, q).groupBy("query_id").agg(F.avg("similarity").alias("s"), F.count("*").alias("n"))
    dense_row = first.agg(F.round(F.avg("s"), 6).alias("s_at_k"), F.sum("n").alias("n")).select(F.lit("projection").alias("family"), F.lit(64).alias("hashes_per_token"), "s_at_k", F.round(F.col("n") / F.lit(answers * q.count()), 6).alias("coverage"))
    return workloads.hash_families(doc_sets(s, d), asked(doc_sets(s, d)), answers=answers).unionByName(dense_row)


WAYS = {"minhash": {"family": "minhash"}, "per_bin": {}, "rotation": {"coin": "always_right"}, "closest": {"coin": "closest_side"}, "offset": {"offset": True}, "interleave": {"layout": "interleave"}}
WAYS_SQL = [Build().buckets(1, 24, 1, **o).queries().counts().hits(10).graded().select(f"SELECT '{n}' AS family, CAST({24 if n == 'minhash' else 1} AS INTEGER) hashes_per_token, s_at_k, coverage FROM graded") for n, o in WAYS.items()]
WAYS_SQL.append(f"""{projected_sql()}, first AS (SELECT * FROM hit JOIN near USING (query_id, id) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) <= 10),
 per AS (SELECT query_id, avg(c) s, count(*) n FROM first GROUP BY query_id) SELECT 'projection' AS family, CAST(64 AS INTEGER) hashes_per_token, round(avg(s), 6) s_at_k, round(sum(n) / (10 * CAST((SELECT count(*) FROM vec WHERE id % 100 = 0) AS DOUBLE)), 6) coverage FROM per""")
add("w13_hash_families", union_all(WAYS_SQL))(family_quality)
#: K and L of a grid, and those the closed forms give for 10,000 rows.
GRID = (*[(k, t) for k in (1, 2, 4) for t in (8, 24)], *dict.fromkeys(theory.theorem_setting(10_000, p1, p2) for p1, p2 in ((0.8, 0.3), (0.9, 0.4))))


def setting_sql(k, t):
    b = Build().buckets(k, t, 1).queries().counts().hits(10).graded()
    return b.select(f"SELECT CAST({k} AS INTEGER) k, CAST({t} AS INTEGER) AS tables, s_at_k, coverage, round((SELECT count(*) FROM counts) / CAST(queries AS DOUBLE), 3) candidates FROM graded")


add("w15_parameter_sweep", union_all([setting_sql(k, t) for k, t in GRID]))(lambda s, d: workloads.parameter_sweep(doc_sets(s, d), asked(doc_sets(s, d)), GRID))
