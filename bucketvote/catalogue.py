"""All registered queries of the engine, each with the SQL that must give the same rows, where SQL can."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import features, hashing, similarity
from .operators import duplicates, pairs
from .operators import search as S
from .operators import sketch
from .oracle import LINE_SETS, Build, num, sets, uni, union_all, words
from .plans import measures, theory
from .registry import add
from .sources.shared import stored
from .sources.tables import balanced, load

SALTED = num("concat_ws('/', id, table_id)")

K, TABLES, NODES, DEPTH, WIDTH = 2, 12, 4, 2, 256


def doc_sets(spark, d, mode="word", n=3):
    return features.token_sets(balanced(load(spark, d, "documents").select("doc_id", "text")), "doc_id", "text", mode, n)


def doc_lines(spark, d):
    rows = balanced(load(spark, d, "documents").select("doc_id", "text"))
    return rows.select(F.col("doc_id").alias("id"), features.word_line(F.col("text")).alias("line")).where("line <> ''")


def asked(rows: DataFrame, n: int | None = None) -> DataFrame:
    """The query rows: ids divisible by 100. With n, a sample instead: the n rows of least hash."""
    if n is None:
        return rows.where(F.col("id") % 100 == 0)
    return rows.orderBy(hashing.token_number(F.col("id")), "id").limit(n)


def digest(rows: DataFrame) -> DataFrame:
    """A set per row as its size and the sum of its tokens' numbers."""
    return rows.select("id", F.size("tokens").cast("long").alias("n"), F.aggregate(F.transform("tokens", hashing.token_number), F.lit(0).cast("long"), lambda s, x: s + x).alias("total"))


DIGEST = f"SELECT id, count(*) n, CAST(sum({num('token')}) AS BIGINT) total FROM sets GROUP BY id"

def shingles_sql(n: int = 3, *table: str) -> str:
    run = " || ' ' || ".join(["w", *[f"lead(w, {i}) OVER p" for i in range(1, n)]])
    return f"""SELECT DISTINCT id, token FROM (SELECT id, CASE WHEN c >= {n} THEN {run} ELSE string_agg(w, ' ') OVER (PARTITION BY id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) END token
  FROM (SELECT id, token w, pos, count(*) OVER (PARTITION BY id) c FROM {words(*table)} WHERE token <> '') WINDOW p AS (PARTITION BY id ORDER BY pos)) WHERE token IS NOT NULL"""


BASKETS = "SELECT DISTINCT o_custkey id, CAST(l_partkey AS VARCHAR) token FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
PROFILES = "SELECT DISTINCT user_id id, event_type || ':' || coalesce(json_extract_string(props, '$.k'), '') token FROM events WHERE user_id IS NOT NULL"
PAGES = "(SELECT page_id, regexp_replace(regexp_replace(regexp_replace(lower(html), '<script[^>]*>.*?</script>', ' ', 'g'), '<style[^>]*>.*?</style>', ' ', 'g'), '<[^>]*>', ' ', 'g') t FROM pages)"

# features
add("f01_doc_words", Build().select(DIGEST))(lambda s, d: digest(doc_sets(s, d)))
add("f02_doc_shingles", Build(shingles_sql()).select(DIGEST))(lambda s, d: digest(doc_sets(s, d, "shingle")))
add("f03_char_grams", Build("SELECT DISTINCT doc_id id, substr(lower(text), i, 5) token FROM (SELECT doc_id, text, unnest(range(1, length(lower(text)) - 3)) i FROM documents) WHERE length(lower(text)) >= 5").select(DIGEST))(lambda s, d: digest(doc_sets(s, d, "char", 5)))
add("f04_hash_features", Build(LINE_SETS).select(f"SELECT id, count(DISTINCT {num('token')} % 1048576) n, CAST(sum(DISTINCT {num('token')} % 1048576) AS BIGINT) total FROM sets GROUP BY id"))(
    lambda s, d: features.hash_features(load(s, d, "lineitem"), features.line_id(), features.line_values()).select("id", F.size("idx").cast("long").alias("n"), F.aggregate("idx", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))
)
add("f04_line_rows", Build(LINE_SETS).select(DIGEST))(lambda s, d: digest(features.line_rows(load(s, d, "lineitem"))))
add("f05_baskets", Build(BASKETS).select(DIGEST))(lambda s, d: digest(features.baskets(load(s, d, "orders"), load(s, d, "lineitem"))))
add("f06_event_profiles", Build(PROFILES).select(DIGEST))(lambda s, d: digest(features.event_profiles(load(s, d, "events"))))
WEIGHTED = f"SELECT id, token, count(*) weight FROM {words()} WHERE token <> '' GROUP BY ALL"


def weighted(s, d):
    return features.weighted_vectors(load(s, d, "documents"), "doc_id", "text")


def word_lists(s, d):
    """All words of each document, with repeats."""
    rows = balanced(load(s, d, "documents").select("doc_id", "text"))
    return rows.select(F.col("doc_id").alias("id"), features.words(F.col("text")).alias("tokens")).where(F.size("tokens") > 0)


add("f07_weighted", WEIGHTED)(weighted)
add("f08_page_text", Build(sets(PAGES, "page_id", "t")).select(DIGEST))(lambda s, d: digest(features.token_sets(load(s, d, "pages").select("page_id", features.page_text(F.col("html")).alias("t")), "page_id", "t")))
add("f09_quantise", "SELECT id, count(*) n, CAST(sum(" + num("token") + ") AS BIGINT) total FROM (SELECT vec_id id, CAST(i - 1 AS VARCHAR) || ':' || CAST(CAST(floor(CAST(x AS DOUBLE) / 0.1) AS BIGINT) AS VARCHAR) token FROM (SELECT vec_id, unnest(embedding) x, generate_subscripts(embedding, 1) i FROM embeddings)) GROUP BY id")(lambda s, d: digest(features.quantise_dense(load(s, d, "embeddings"), "vec_id", "embedding")))
add("f10_binarise", f"SELECT id, token FROM ({WEIGHTED})")(lambda s, d: features.binarise(weighted(s, d)))
add("f11_norms", f"SELECT id, round(sqrt(sum(weight * weight)), 6) norm, count(*) size FROM ({WEIGHTED}) GROUP BY id")(lambda s, d: features.vector_norms(weighted(s, d)).select("id", F.round("norm", 6).alias("norm"), "size"))


def ml_vectors(s, d):
    """The library's sparse vectors: size, indices and values."""
    v = F.unwrap_udt(F.col("features"))
    return features.to_ml_vector(doc_sets(s, d)).select("id", v["size"].alias("size"), v["indices"].alias("indices"), v["values"].alias("values"))


add("f12_ml_vector")(ml_vectors)

# hashes and signatures
A0, B0 = hashing.hash_coefficients(1, 1)[0]
add("h01_hash", Build().select(f"SELECT id, token, {uni(num('token'), A0, B0)} h FROM sets"))(lambda s, d: doc_sets(s, d).select("id", F.explode("tokens").alias("token")).select("id", "token", hashing.hash_column(F.col("token"), 0).alias("h")))
CO = hashing.hash_coefficients(1, 8)
SIG_DIGEST = 'SELECT id, CAST(bin AS INTEGER) bin, value FROM {}'


def long_sig(sig):
    return sig.select("id", F.posexplode("sig").alias("bin", "value"))


add("h02_minhash", Build().select(" UNION ALL ".join(f"SELECT id, CAST({i} AS INTEGER) bin, min({uni(num('token'), a, b)}) AS value FROM sets GROUP BY id" for i, (a, b) in enumerate(CO))))(lambda s, d: long_sig(hashing.minhash(doc_sets(s, d), 8)))
add("h04_one_permutation", Build().signature(24).select(SIG_DIGEST.format("sig")))(lambda s, d: long_sig(hashing.one_permutation(doc_sets(s, d), 24)).where("value is not null"))
for _name, _opt in {"per_bin": {}, "rotation": {"coin": "always_right"}, "closest": {"coin": "closest_side"}, "offset": {"offset": True}}.items():
    add(f"h05_densify_{_name}", Build().signature(24).dense(24, **_opt).select(SIG_DIGEST.format("full_sig")))(lambda s, d, o=_opt: long_sig(hashing.densify(hashing.one_permutation(doc_sets(s, d), 24), 24, **o)))
for _name, _layout in {"h06_bucket_keys": "block", "h06_bucket_keys_interleave": "interleave"}.items():
    add(_name, Build().signature(24).dense(24).keys(K, TABLES, _layout).select("SELECT * FROM keys"))(lambda s, d, o=_layout: hashing.keys_of(doc_sets(s, d), K, TABLES, layout=o))


def calibration(s, d, family="minhash", bins=64):
    """Mean share of agreeing values by tenth of exact similarity, over pairs that share a word with a query."""
    rows = doc_sets(s, d)
    q = asked(rows)
    sig = (hashing.minhash(rows, bins) if family == "minhash" else hashing.densify(hashing.one_permutation(rows, bins), bins)).withColumnRenamed("sig", "s1")
    pairs = similarity.shared_tokens(rows, q, "jaccard").join(sig, "id").join(sig.select(F.col("id").alias("query_id"), F.col("s1").alias("s2")), "query_id")
    return pairs.groupBy(F.floor(F.col("similarity") * 10).alias("tenth")).agg(F.count("*").alias("pairs"), F.round(F.avg("similarity"), 6).alias("jaccard"), F.round(F.avg(hashing.jaccard_estimate(F.col("s1"), F.col("s2"))), 6).alias("agreement"))


JACCARD = "shared / CAST(na + nb - shared AS DOUBLE)"
TENTHS = f"SELECT CAST(floor({JACCARD} * 10) AS BIGINT) tenth, count(*) pairs, round(avg({JACCARD}), 6) jaccard, round(avg(rate), 6) agreement FROM agreed GROUP BY ALL"
add("h03_jaccard_estimate", Build().asked().minhash(64).pairs().agreement().select(TENTHS))(calibration)
add("h09_calibration", Build().asked().signature(64).dense(64).pairs().agreement().select(TENTHS))(lambda s, d: calibration(s, d, "one_permutation"))
#: (vec_id, bit, sign) of random projections, the directions from the engine's seed
SIGNS = "SELECT vec_id id, CAST({i} AS INTEGER) bin, CAST(list_dot_product(CAST(embedding AS DOUBLE[]), [{r}]) >= 0 AS BIGINT) AS value FROM embeddings WHERE embedding IS NOT NULL"


def signs_sql(bits, dims):
    return " UNION ALL ".join(SIGNS.format(i=i, r=", ".join(f"{x!r}::DOUBLE" for x in row)) for i, row in enumerate(hashing.directions(bits, dims)))


add("h07_signed_projection", signs_sql(16, 64))(lambda s, d: long_sig(hashing.signed_projection(load(s, d, "embeddings"), "vec_id", "embedding", 16, 64)))


def euclidean_buckets(s, d):
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    v = load(s, d, "embeddings").select("vec_id", array_to_vector(F.col("embedding").cast("array<double>")).alias("v"))
    return BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=0.5, numHashTables=4, seed=1).fit(v).transform(v).select("vec_id", F.transform("h", lambda x: F.unwrap_udt(x)["values"][0].cast("long")).alias("buckets"))


add("h08_euclidean")(euclidean_buckets)

# similarities
def asked_build(set_sql=None, n=None):
    return Build(set_sql).asked(n)


COS, JAC = "shared / sqrt(CAST(na * nb AS DOUBLE))", "shared / CAST(na + nb - shared AS DOUBLE)"


def best(value, k=10, src="sim_rows"):
    return f'SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY round({value}, 9) DESC, id) AS INTEGER) AS "rank", id, round({value}, 6) similarity FROM {src} QUALIFY "rank" <= {k}'


def top_by(rows, k=10):
    order = Window.partitionBy("query_id").orderBy(F.desc(F.round("similarity", 9)), "id")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", F.round("similarity", 6).alias("similarity"))


add("m01_jaccard_top", asked_build().pairs().select(best(JAC)))(lambda s, d: S.brute_force(doc_sets(s, d), asked(doc_sets(s, d)), 10, "jaccard"))
add("m02_cosine_top", asked_build().pairs().select(best(COS)))(lambda s, d: S.brute_force(doc_sets(s, d), asked(doc_sets(s, d)), 10))
WCOS = (
    Build(f"SELECT id, token, weight FROM ({WEIGHTED})").asked()
    .add("norms", "SELECT id, sqrt(sum(weight * weight)) norm FROM sets GROUP BY id")
    .add("sim_rows", "SELECT a.id query_id, b.id, sum(a.weight * b.weight) / (any_value(na.norm) * any_value(nb.norm)) s FROM sets a JOIN sets b ON a.token = b.token AND a.id <> b.id JOIN norms na ON na.id = a.id JOIN norms nb ON nb.id = b.id WHERE a.id IN (SELECT query_id FROM asked) GROUP BY ALL")
    .select(best("s"))
)
add("m02_weighted_cosine_top", WCOS)(lambda s, d: S.brute_force(word_lists(s, d), asked(word_lists(s, d)), 10, "weighted"))


def dense_top(s, d):
    """Dense cosine of the query rows with all vectors."""
    v = load(s, d, "embeddings").where("embedding is not null").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    return top_by(similarity.dense_pairs(v, asked(v)))


add("m03_dense_top", f"""WITH p AS (SELECT vec_id id, unnest(embedding) x, generate_subscripts(embedding, 1) i FROM embeddings), n AS (SELECT id, sum(CAST(x AS DOUBLE) * x) s FROM p GROUP BY id),
 q AS (SELECT id FROM n WHERE id % 100 = 0), sim_rows AS (SELECT a.id query_id, b.id, sum(CAST(a.x AS DOUBLE) * b.x) / sqrt(any_value(na.s) * any_value(nb.s)) s FROM p a JOIN p b ON a.i = b.i AND a.id <> b.id JOIN n na ON na.id = a.id JOIN n nb ON nb.id = b.id WHERE a.id IN (SELECT id FROM q) GROUP BY ALL) {best('s')}""")(dense_top)


def distances(s, d):
    top = pairs.ranked(doc_sets(s, d), asked(doc_sets(s, d)), 3)
    euclidean = F.sqrt((F.col("nq") + F.col("nd") - 2 * F.col("dot")).cast("double"))  # of the sets' indicator vectors
    far = {"jaccard": 1 - pairs.similarity("jaccard"), "cosine": 1 - pairs.similarity(), "euclidean": euclidean}
    return top.select("query_id", "id", *[F.round(x, 6).alias(n) for n, x in far.items()])


add("m04_distances", asked_build().pairs().add("best3", f'SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round({COS}, 9) DESC, id) AS rk FROM sim_rows QUALIFY rk <= 3').select(f"SELECT query_id, id, round(1 - {JAC}, 6) jaccard, round(1 - {COS}, 6) cosine, round(sqrt(CAST(na + nb - 2 * shared AS DOUBLE)), 6) euclidean FROM best3"))(distances)


# index
def buckets(s, d, nodes=NODES, **o):
    return S.build_bucket_index(doc_sets(s, d), K, TABLES, nodes, **o)


def qkeys(s, d, **o):
    return S.hash_queries(asked(doc_sets(s, d)), K, TABLES, **o)


def cells(s, d, nodes=NODES):
    return S.build_sketch_index(buckets(s, d, nodes), DEPTH, WIDTH)


def B(nodes=NODES, **o):
    return Build().buckets(K, TABLES, nodes, **o)


def BC(nodes=NODES):
    return B(nodes).cells(DEPTH, WIDTH).queries()


CELL_COLS = 'table_id, bucket_key, node, "row", col, total, cand, votes'
add("x01_nodes", Build().select(f"SELECT DISTINCT id, CAST({num('id')} % {NODES} AS INTEGER) node FROM sets"))(lambda s, d: S.assign_nodes(doc_sets(s, d), NODES).select("id", "node"))
add("x02_bucket_index", B().select("SELECT * FROM buckets"))(buckets)


def union_law(s, d):
    """Rows by which the united node indexes differ from the one index, both ways: none."""
    one, many = buckets(s, d, 1).drop("node"), None
    for node in range(NODES):
        part = S.assign_nodes(doc_sets(s, d), NODES).where(F.col("node") == node).drop("node")
        own = hashing.keys_of(part, K, TABLES).select("table_id", "bucket_key", "id")
        many = own if many is None else many.unionByName(own)
    return one.exceptAll(many).unionByName(many.exceptAll(one)).agg(F.count("*").alias("differing"))


add("x03_union_law", "SELECT CAST(0 AS BIGINT) differing")(union_law)
add("x04_reservoir", B().select(f"SELECT node, table_id, bucket_key, id FROM buckets QUALIFY row_number() OVER (PARTITION BY node, table_id, bucket_key ORDER BY {SALTED}, id) <= 4"))(lambda s, d: S.build_reservoir_index(buckets(s, d), 4))
add("x05_sketch_cells", B().cells(DEPTH, WIDTH).select(f"SELECT {CELL_COLS} FROM cells"))(cells)
add("x06_hybrid_light", B().add("sized", "SELECT *, count(*) OVER (PARTITION BY node, table_id, bucket_key) n FROM buckets").select("SELECT node, table_id, bucket_key, id FROM sized WHERE n <= 4"))(lambda s, d: S.build_hybrid_index(buckets(s, d), 4)[0])
add("x06_hybrid_heavy", B().add("sized", "SELECT *, count(*) OVER (PARTITION BY node, table_id, bucket_key) n FROM buckets").add("heavy", "SELECT * EXCLUDE (n) FROM sized WHERE n > 4").cells(DEPTH, WIDTH, "heavy").select(f"SELECT {CELL_COLS} FROM cells"))(lambda s, d: S.build_hybrid_index(buckets(s, d), 4, DEPTH, WIDTH)[1])


def appended(s, d):
    b = buckets(s, d)
    half = F.col("id") % 2 == 0
    both = S.append_index(S.build_sketch_index(b.where(half), DEPTH, WIDTH), S.build_sketch_index(b.where(~half), DEPTH, WIDTH))
    return both.select("node", "table_id", "bucket_key", "row", "col", "total")


def appended_cells(s, d):
    """All of a merged index: totals, candidates and votes."""
    b = buckets(s, d)
    half = F.col("id") % 2 == 0
    return S.append_index(S.build_sketch_index(b.where(half), DEPTH, WIDTH), S.build_sketch_index(b.where(~half), DEPTH, WIDTH))


PLACE = "node, table_id, bucket_key"
HALVES = B().add("even", "SELECT * FROM buckets WHERE id % 2 = 0").add("odd", "SELECT * FROM buckets WHERE id % 2 <> 0").cells(DEPTH, WIDTH, "even", "c0").cells(DEPTH, WIDTH, "odd", "c1").add("halves", "SELECT * FROM c0 UNION ALL SELECT * FROM c1").merge("merged", "halves", PLACE)
add("x07_append_cells", HALVES.select(f'SELECT {PLACE}, "row", col, total, cand, votes FROM merged'))(appended_cells)
ARRIVAL = Build().buckets(K, TABLES, NODES)
ARRIVAL.add("sp", ARRIVAL.spread("buckets", DEPTH, WIDTH)).add("seen", f'SELECT {PLACE}, "row", col, id, count(*) OVER w total, row_number() OVER (w ORDER BY id DESC) n FROM sp WINDOW w AS (PARTITION BY {PLACE}, "row", col)')
add("x05_sketch_arrival", ARRIVAL.select(f'SELECT {PLACE}, "row", col, CAST(total AS BIGINT) total, id cand, CAST(total % 2 AS BIGINT) votes FROM seen WHERE n = 2 - total % 2'))(lambda s, d: sketch.arrival_cells(buckets(s, d), ["node", "table_id", "bucket_key"], DEPTH, WIDTH))
add("x07_append_totals", B().cells(DEPTH, WIDTH).select('SELECT node, table_id, bucket_key, "row", col, total FROM cells'))(appended)
STATS = 'SELECT table_id, count(*) buckets, CAST(sum(n) AS BIGINT) ids, max(n) largest, count(*) FILTER (n = 1) singletons, round(sum(CASE WHEN n > 8 THEN n ELSE 0 END) / CAST(sum(n) AS DOUBLE), 6) heavy_share FROM (SELECT table_id, bucket_key, count(*) n FROM buckets GROUP BY ALL) GROUP BY table_id'
add("x09_stats", B().select(STATS))(lambda s, d: measures.index_stats(buckets(s, d)))
add("x09_stats_lines", Build(LINE_SETS).buckets(4, 8, NODES).select(STATS))(lambda s, d: measures.index_stats(S.build_bucket_index(features.line_rows(load(s, d, "lineitem")), 4, 8, NODES)))


# sketches and search
def local(s, d, nodes=NODES):
    return S.local_merge(qkeys(s, d), cells(s, d, nodes))


MERGED_COLS = 'query_id, "row", col, total, cand, votes'
add("q01_query_keys", B().queries().select("SELECT * FROM qkeys"))(qkeys)
add("q03_local_merge", BC().local().select("SELECT * FROM local_cells"))(local)
add("s03_multiway_merge", BC().local().merge("merged", "local_cells", "query_id").select(f"SELECT {MERGED_COLS} FROM merged"))(lambda s, d: S.global_merge(local(s, d), NODES, "multiway"))
for _m in (2, 4, 7):
    for _s in ("tree", "linear"):
        add(f"q0{4 if _s == 'tree' else 5}_{_s}_m{_m}", getattr(BC(_m).local(), _s)(_m).select(f"SELECT {MERGED_COLS} FROM merged"))(lambda s, d, m=_m, st=_s: S.global_merge(local(s, d, m), m, st))
add("a02_tree_fan_in_3", BC(7).local().select('SELECT query_id, "row", col, CAST(sum(total) AS BIGINT) total FROM local_cells GROUP BY ALL'))(lambda s, d: S.global_merge(local(s, d, 7), 7, "tree", 3).select("query_id", "row", "col", "total"))
add("q04_array_m7", BC(7).local().tree(7).select(f"SELECT {MERGED_COLS} FROM merged"))(lambda s, d: S.global_merge(local(s, d, 7), 7, "array"))
add("q06_exact_counts", B().queries().counts().select("SELECT * FROM counts"))(lambda s, d: S.exact_counts(qkeys(s, d), buckets(s, d)))
for _s in ("tree", "linear"):
    add(f"q09_search_{_s}", getattr(BC().local(), _s)(NODES).top(10, DEPTH, WIDTH).select('SELECT query_id, "rank", id, votes, upper FROM answers'))(lambda s, d, st=_s: S.search(doc_sets(s, d), asked(doc_sets(s, d)), K, TABLES, 10, NODES, st, DEPTH, WIDTH))
HITS = 'SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) AS INTEGER) AS "rank", id, hits votes, hits AS upper FROM counts WHERE query_id <> id QUALIFY "rank" <= 10'
add("q09_search_exact", B().queries().counts().select(HITS))(lambda s, d: S.search(doc_sets(s, d), asked(doc_sets(s, d)), K, TABLES, 10, NODES, "exact"))
add("q14_search_reservoir", B().add("kept", f"SELECT * FROM buckets QUALIFY row_number() OVER (PARTITION BY node, table_id, bucket_key ORDER BY {SALTED}, id) <= 8").queries().counts("kept").select(HITS))(lambda s, d: S.search(doc_sets(s, d), asked(doc_sets(s, d)), K, TABLES, 10, NODES, "reservoir", cap=8))
add("s06_top_k", BC().local().merge("merged", "local_cells", "query_id").top(5, DEPTH, WIDTH, False).select('SELECT query_id, "rank", id, upper, votes FROM answers'))(lambda s, d: sketch.top_k(S.global_merge(local(s, d), NODES, "multiway"), ["query_id"], 5, DEPTH, WIDTH))


def bounds(s, d):
    merged = S.global_merge(local(s, d), NODES, "multiway")
    return sketch.estimate(merged, merged.select("query_id", F.col("cand").alias("id")).distinct(), ["query_id"], DEPTH, WIDTH)


add("s05_bounds", BC().local().merge("merged", "local_cells", "query_id").top(5, DEPTH, WIDTH, False).select("SELECT query_id, id, CAST(upper AS BIGINT) AS upper, CAST(votes AS BIGINT) votes FROM bounds"))(bounds)
add("s07_heavy_hitters", BC().local().merge("merged", "local_cells", "query_id").top(5, DEPTH, WIDTH, False).add("alls", 'SELECT query_id, sum(total) a FROM merged WHERE "row" = 0 GROUP BY ALL').select("SELECT b.query_id, id, CAST(upper AS BIGINT) AS upper, CAST(votes AS BIGINT) votes FROM bounds b JOIN alls USING (query_id) WHERE upper >= 0.02 * a"))(lambda s, d: sketch.heavy_hitters(S.global_merge(local(s, d), NODES, "multiway"), ["query_id"], 0.02, DEPTH, WIDTH))


def event_ids(s, d):
    return load(s, d, "events").where("user_id is not null").select(F.col("user_id").alias("id"), "event_type")


EV = Build("SELECT user_id id, event_type token FROM events WHERE user_id IS NOT NULL")
add("s08_count_min", EV.add("ev", "SELECT id, token event_type FROM sets").add("sp", EV.spread("ev", 2, 64)).select('SELECT event_type, "row", col, count(*) total FROM sp GROUP BY ALL'))(lambda s, d: sketch.count_min(event_ids(s, d), ["event_type"], 2, 64))
EV2 = Build("SELECT user_id id, event_type token FROM events WHERE user_id IS NOT NULL")
add("s10_count_sketch", EV2.add("ev", "SELECT id, token event_type FROM sets").add("sp", EV2.spread("ev", 3, 64)).select('SELECT event_type, "row", col, CAST(sum(1 - 2 * (' + num("concat_ws('/', id, \"row\")") + ' % 2)) AS BIGINT) total FROM sp GROUP BY ALL'))(lambda s, d: sketch.count_sketch(event_ids(s, d), ["event_type"], 3, 64))
add("s09_frequent_items")(lambda s, d: event_ids(s, d).stat.freqItems(["id"], 0.02))
add("s12_approx_top_k")(lambda s, d: event_ids(s, d).groupBy("event_type").agg(F.expr("approx_top_k(id, 5)").alias("top")))

# baselines
def classic_sql(least, k=K, tables=TABLES):
    b = Build().buckets(k, tables, 1).queries().counts().pairs()
    return b.add("hit", f"SELECT s.* FROM sim_rows s JOIN counts c ON c.query_id = s.query_id AND c.id = s.id WHERE c.hits >= {least}").select(best(COS, 10, "hit"))


for _name, _least in {"q07_classic_lsh": 1, "q08_filtered_lsh": 3}.items():
    add(_name, classic_sql(_least))(lambda s, d, n=_least: S.classic_lsh(doc_sets(s, d), asked(doc_sets(s, d)), K, TABLES, 10, n))
add("b04_or_only_lsh", classic_sql(1, 1, 12))(lambda s, d: S.classic_lsh(doc_sets(s, d), asked(doc_sets(s, d)), 1, 12, 10))
add("b01_brute_force", asked_build().pairs().select(best(COS, 64)))(lambda s, d: S.brute_force(doc_sets(s, d), asked(doc_sets(s, d)), 64))


def ml_hashed(s, d):
    """(id, tokens, keys): the built-in LSH's vectors and hashes; tokens are a vector's indices, keys its hashes, each with its table.

    Sets are stored first: the library's functions fail on a text without a word, and the optimizer may run them before the filter that leaves such rows out.
    """
    from pyspark.ml.feature import MinHashLSH

    v = features.to_ml_vector(stored(doc_sets(s, d), "sets")).select("id", "features")
    model = MinHashLSH(inputCol="features", outputCol="h", numHashTables=8, seed=1).fit(v)
    hashes = F.transform("h", lambda h, i: F.concat(i.cast("string"), F.lit(":"), F.unwrap_udt(h)["values"][0].cast("long").cast("string")))
    return model.transform(v).select("id", F.unwrap_udt("features")["indices"].alias("tokens"), hashes.alias("keys"))


def ml_met(rows, q, k):
    """Pairs that share a built-in hash, with 1 less their built-in distance: at least a query's k nearest."""
    return pairs.met(rows, q, "jaccard", top=k, min_hits=1).select("query_id", "id", (1 - (1 - pairs.similarity("jaccard"))).alias("similarity"))


def ml_join(s, d, k=10):
    """The built-in LSH as a batch join, the best by distance. Its own join carries both vectors of every candidate pair through a shuffle; here its hashes meet in blocks inside tasks, which gives the same pairs."""
    rows = ml_hashed(s, d)
    return top_by(ml_met(rows, asked(rows), k).where("1 - similarity < 0.95"), k)


add("b03_builtin_lsh_join")(ml_join)


def ml_single(s, d, n=100, k=10):
    """The built-in LSH's nearest neighbours of single queries. The experiment is of 100 such queries, so n are asked at most. All are answered in one reading of the rows; of equal distances the smaller id comes first."""
    rows = ml_hashed(s, d)
    first = asked(rows.select("id")).orderBy("id").limit(n)
    near = ml_met(rows, asked(rows).join(first, "id", "left_semi"), k)
    order = Window.partitionBy("query_id").orderBy(F.desc(F.round("similarity", 9)), "id")
    return near.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).drop("r")


add("b02_builtin_lsh_single")(ml_single)


# near-duplicates, measures, theory
WORDS = 5
RAW = f"raw AS ({shingles_sql(WORDS)}), fp AS (SELECT id, string_agg(token, chr(31) ORDER BY token) f FROM raw GROUP BY id), copies AS (SELECT id, min(id) OVER (PARTITION BY f) rep FROM fp)"
NEAR = (
    Build(f"WITH {RAW} SELECT id, token FROM raw WHERE id IN (SELECT rep FROM copies)").buckets(2, 16, 1)
    .add("hits", "SELECT a.id id_a, b.id id_b, count(*) hits FROM buckets a JOIN buckets b USING (table_id, bucket_key) WHERE a.id < b.id GROUP BY ALL")
    .add("sizes", "SELECT id, count(*) n FROM sets GROUP BY id")
    .add("common", "SELECT h.id_a, h.id_b, any_value(h.hits) hits, count(b.token) c FROM hits h JOIN sets a ON a.id = h.id_a LEFT JOIN sets b ON b.id = h.id_b AND b.token = a.token GROUP BY h.id_a, h.id_b")
    .add("linked", "SELECT id_a, id_b, hits, round(c / CAST(x.n + y.n - c AS DOUBLE), 6) jaccard FROM common JOIN sizes x ON x.id = id_a JOIN sizes y ON y.id = id_b WHERE round(c / CAST(x.n + y.n - c AS DOUBLE), 6) >= 0.8")
)
add("q12_near_duplicates", NEAR.select("SELECT * FROM linked"))(lambda s, d: duplicates.text_links(doc_lines(s, d), WORDS, 2, 16))
CLASSES = (
    NEAR.add("sides", "SELECT id_a a, id_b b FROM linked UNION SELECT id_b, id_a FROM linked")
    .add("walk", "SELECT a, a root FROM sides UNION SELECT sides.b, walk.root FROM walk JOIN sides USING (a)")
    .add("least", "SELECT a, min(root) class_id FROM walk GROUP BY a")
    .add("met", f"SELECT c.id, coalesce(class_id, rep) class_id FROM (WITH {RAW} SELECT * FROM copies) c LEFT JOIN least ON a = rep")
    .add("bare", "SELECT doc_id, CASE WHEN trim(text) <> '' THEN min(doc_id) OVER (PARTITION BY md5(text)) ELSE doc_id END AS same FROM documents WHERE doc_id NOT IN (SELECT id FROM met)")
    .select("SELECT * FROM met UNION ALL SELECT doc_id, same FROM bare")
)


def near_classes(s, d):
    """(id, class_id) of every document; equal texts without a word share a class, empty ones stay alone."""
    met = duplicates.classes(doc_sets(s, d, "shingle", WORDS), 2, 16)
    rest = load(s, d, "documents").select(F.col("doc_id").alias("id"), F.when(F.trim("text") != "", F.md5("text")).alias("t")).join(met.select("id"), "id", "left_anti")
    least = rest.where("t is not null").groupBy("t").agg(F.min("id").alias("class_id"))
    return met.unionByName(rest.join(least, "t", "left").select("id", F.coalesce("class_id", "id").alias("class_id")))


add("q12_classes", CLASSES)(near_classes)


def quality(s, d, strategy="tree", nodes=NODES, ks=(1, 64), missing="ignore", k=1, tables=TABLES):
    rows = doc_sets(s, d)
    q = asked(rows)
    return measures.similarity_at_k(S.search(rows, q, k, tables, max(ks), nodes, strategy, 2, 1024), rows, q, ks, missing).select(F.lit(strategy).alias("strategy"), F.lit(nodes).alias("nodes"), "k", "s_at_k", "coverage", "queries")


def quality_sql(missing):
    asked_n = "(SELECT count(*) FROM asked)"
    value = "avg(s / n)" if missing == "ignore" else f"sum(s / k) / {asked_n}"
    b = Build().buckets(1, TABLES, NODES).queries().counts().pairs().add("placed", 'SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) AS rk, id FROM counts WHERE query_id <> id QUALIFY rk <= 64')
    b.add("scored", f"SELECT p.query_id, p.rk, k, coalesce({COS}, 0) sim FROM placed p LEFT JOIN sim_rows s ON s.query_id = p.query_id AND s.id = p.id, (VALUES (1), (64)) t(k) WHERE rk <= k")
    return b.select(f"SELECT 'exact' strategy, CAST({NODES} AS INTEGER) nodes, CAST(k AS INTEGER) k, round({value}, 6) s_at_k, round(sum(n) / CAST(k * {asked_n} AS DOUBLE), 6) coverage, CAST({asked_n} AS BIGINT) queries FROM (SELECT k, query_id, sum(sim) s, count(*) n FROM scored GROUP BY ALL) GROUP BY k")


for _m in ("ignore", "zero"):
    add(f"c01_s_at_k_{_m}", quality_sql(_m))(lambda s, d, m=_m: quality(s, d, "exact", missing=m))
RECALL = Build().buckets(1, TABLES, NODES).queries().counts().pairs()
RECALL.add("truth", f"SELECT query_id, id FROM sim_rows QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round({COS}, 9) DESC, id) <= 10")
RECALL.add("got", "SELECT query_id, id FROM counts WHERE query_id <> id QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) <= 10")
add("c03_recall", RECALL.select("SELECT CAST(10 AS INTEGER) k, found, wanted, round(found / CAST(wanted AS DOUBLE), 6) recall FROM (SELECT count(*) found FROM truth SEMI JOIN got USING (query_id, id)), (SELECT count(*) wanted FROM truth)"))(lambda s, d: measures.recall_at_k(S.search(doc_sets(s, d), asked(doc_sets(s, d)), 1, TABLES, 10, NODES, "exact"), S.brute_force(doc_sets(s, d), asked(doc_sets(s, d)), 10), 10))
add("c04_random_pairs", asked_build(n=200).pairs("a.id < b.id").add("few", "SELECT * FROM sim_rows WHERE id IN (SELECT query_id FROM asked)").select(f"SELECT CAST(19900 AS BIGINT) pairs, round(sum({COS}) / 19900, 6) mean_cosine FROM few"))(lambda s, d: measures.random_pair_similarity(doc_sets(s, d), 200))
add("c07_merge_cost", B().queries().select(f"SELECT query_id, count(DISTINCT (node, b.table_id, b.bucket_key)) sketches, CAST({S.tree_rounds(NODES)} AS BIGINT) rounds, CAST({NODES - 1} AS BIGINT) linear_merges FROM qkeys q JOIN buckets b USING (table_id, bucket_key) GROUP BY ALL"))(lambda s, d: measures.merge_cost(qkeys(s, d), buckets(s, d), NODES))


def distance_count(s, d):
    c = S.exact_counts(qkeys(s, d), buckets(s, d)).agg(F.count("*").alias("n"))
    # the reach of each method: what it meets, every pair, and the sketch's cells, which hold counts and no vector
    n = doc_sets(s, d).agg((F.count("*") * F.sum((F.col("id") % 100 == 0).cast("long"))).alias("n"))
    return c.select(F.lit("classic").alias("method"), "n").unionByName(n.select(F.lit("brute").alias("method"), "n")).unionByName(c.select(F.lit("sketch").alias("method"), F.lit(0).cast("long").alias("n")))


add("c08_distances", B().queries().counts().select(f"SELECT 'classic' AS method, count(*) n FROM counts UNION ALL SELECT 'brute', count(DISTINCT id) * count(DISTINCT id) FILTER (id % 100 = 0) FROM sets UNION ALL SELECT 'sketch', 0"))(distance_count)
add("c09_multiplications", Build().select("SELECT count(*) per_query, count(DISTINCT id) n FROM sets"))(lambda s, d: doc_sets(s, d).agg(F.sum(F.size("tokens")).alias("per_query"), F.count("*").alias("n")))


def volume(s, d):
    by_node = S.probe(qkeys(s, d), buckets(s, d)).groupBy("query_id", "node", "id").agg(F.count("*").alias("hits"))
    return measures.communication_volume(local(s, d), by_node, NODES)


add("c10_communication", BC().local().add("per", "SELECT DISTINCT q.query_id, node, b.id FROM qkeys q JOIN buckets b USING (table_id, bucket_key)").add("r1", 'SELECT DISTINCT query_id, node // 2 node, "row", col FROM local_cells').select("SELECT 'linear' strategy, count(*) n FROM local_cells WHERE node > 0 UNION ALL SELECT 'exact', count(*) FROM per WHERE node > 0 UNION ALL SELECT 'tree', (SELECT count(*) FROM local_cells WHERE node % 2 = 1) + (SELECT count(*) FROM r1 WHERE node % 2 = 1)"))(volume)
add("c11_footprint", B().cells(DEPTH, WIDTH).select("SELECT 'ids' kind, count(*) n, count(*) * 8 bytes FROM buckets UNION ALL SELECT 'cells', count(*), count(*) * 24 FROM cells"))(lambda s, d: measures.footprint(buckets(s, d), cells(s, d)))
add("c12_imbalance", B().select("SELECT count(*) nodes, max(n) most, round(max(n) / avg(n), 6) imbalance FROM (SELECT node, count(*) n FROM buckets GROUP BY node)"))(lambda s, d: measures.node_imbalance(buckets(s, d)))
add("c15_candidate_fraction", B().queries().counts().select(f"SELECT round(count(*) / CAST((SELECT count(DISTINCT id) * count(DISTINCT id) FILTER (id % 100 = 0) FROM sets) AS DOUBLE), 6) fraction FROM counts"))(lambda s, d: S.exact_counts(qkeys(s, d), buckets(s, d)).agg(F.count("*").alias("c")).crossJoin(doc_sets(s, d).agg((F.count("*") * F.sum((F.col("id") % 100 == 0).cast("long"))).alias("n"))).select(F.round(F.col("c") / F.col("n"), 6).alias("fraction")))
add("c16_sketch_error", BC().local().merge("merged", "local_cells", "query_id").top(10, DEPTH, WIDTH, False).counts().add("e", "SELECT a.*, coalesce(c.hits, 0) hits FROM answers a LEFT JOIN counts c ON c.query_id = a.query_id AND c.id = a.id").select("SELECT count(*) reported, count(*) FILTER (votes <= hits AND hits <= upper) inside, round(avg(upper - hits), 6) mean_over, round(avg(hits - votes), 6) mean_under FROM e"))(lambda s, d: measures.sketch_error(sketch.top_k(S.global_merge(local(s, d), NODES, "multiway"), ["query_id"], 10, DEPTH, WIDTH), S.exact_counts(qkeys(s, d), buckets(s, d))))
CURVE = ", ".join(str(x) for x in theory.SETTINGS)
add("th01_curve", f"SELECT CAST(k AS INTEGER) k, CAST(l AS INTEGER) l, s, lines, round(1 - pow(1 - pow(s, k), l), 6) any_hit, round(l * pow(s, k), 6) expected_hits FROM (VALUES {CURVE}) t(k, l), (SELECT round(l_quantity) / 50 s, count(*) lines FROM lineitem WHERE l_quantity IS NOT NULL GROUP BY 1)")(lambda s, d: theory.collision_curve(load(s, d, "lineitem")))
PCASES = ", ".join(f"({p}::DOUBLE, {q}::DOUBLE)" for p, q in theory.SENSITIVITIES)
SIZED = f"(SELECT o_orderpriority, count(*) n FROM orders GROUP BY 1), (VALUES {PCASES}) t(p1, p2)"
add("th02_parameters", f"SELECT o_orderpriority, n, p1, p2, round(ln(p1) / ln(p2), 6) ratio, round(-ln(p1) / (ln(p1) - ln(p2)), 6) rho, round(ln(n) / (ln(p1) - ln(p2)), 6) k, round(pow(CAST(n AS DOUBLE), -ln(p1) / (ln(p1) - ln(p2))), 4) l, ln(p1) / ln(p2) < 0.5 strong FROM {SIZED}")(lambda s, d: theory.choose_parameters(load(s, d, "orders")))
add("th05_signal_to_noise", f"WITH p AS (SELECT o_orderpriority, n, p1, p2, round(ln(n) / (ln(p1) - ln(p2)), 6) k, round(pow(CAST(n AS DOUBLE), -ln(p1) / (ln(p1) - ln(p2))), 4) l FROM {SIZED}) SELECT o_orderpriority, n, p1, p2, round(l * pow(p1, k), 3) near_signal, round(n * l * pow(p2, k) / l, 3) far_per_table FROM p")(lambda s, d: theory.signal_to_noise(load(s, d, "orders")))
NODE_LOADS = f"(SELECT count(*) m, max(n) most FROM (SELECT t.m dealt, {num('o_orderkey')} % t.m node, count(*) n FROM orders, (VALUES (2), (4), (8), (16), (20)) t(m) GROUP BY ALL) GROUP BY dealt)"
add("th06_cost_model", f"SELECT m, most, 'tree' strategy, m * 32 + m - 1 merges, CAST(ceil(log2(m)) + 5 AS BIGINT) AS depth FROM {NODE_LOADS} UNION ALL SELECT m, most, 'linear', m * 32 + m - 1, m - 1 + 5 FROM {NODE_LOADS}")(lambda s, d: theory.cost_model(load(s, d, "orders")))
add("th07_dedup_limit", "SELECT o_orderpriority, n, p1, round(-ln(p1) / (ln(p1) - ln(0.3::DOUBLE)), 6) rho, round(pow(CAST(n AS DOUBLE), -ln(p1) / (ln(p1) - ln(0.3::DOUBLE))), 4) AS tables FROM (SELECT o_orderpriority, count(*) n FROM orders GROUP BY 1), (VALUES (0.8::DOUBLE), (0.9), (0.99), (0.999)) t(p1)")(lambda s, d: theory.dedup_limit(load(s, d, "orders")))
add("th08_repetitions", "SELECT l_returnflag, failure, success, CAST(ceil(ln(failure) / ln(nullif(1 - success, 0))) AS BIGINT) repetitions FROM (VALUES (0.1::DOUBLE), (0.01), (0.001)) f(failure), (SELECT l_returnflag, count(*) / CAST((SELECT count(*) FROM lineitem) AS DOUBLE) success FROM lineitem GROUP BY 1)")(lambda s, d: theory.boost_repetitions(load(s, d, "lineitem")))


# workloads over the tables; more are in workload_queries
def set_families(s, d):
    """The eight families of sets, each by name."""
    line, pages = load(s, d, "lineitem"), load(s, d, "pages")
    return {
        "documents": doc_sets(s, d), "shingles": doc_sets(s, d, "shingle"), "characters": doc_sets(s, d, "char", 5), "lineitem": features.line_rows(line),
        "baskets": features.baskets(load(s, d, "orders"), line), "events": features.event_profiles(load(s, d, "events")),
        "pages": features.token_sets(pages.select("page_id", features.page_text(F.col("html")).alias("t")), "page_id", "t"), "embeddings": features.quantise_dense(load(s, d, "embeddings"), "vec_id", "embedding", 0.1),
    }


CHARS = "SELECT DISTINCT doc_id id, substr(lower(text), i, 5) token FROM (SELECT doc_id, text, unnest(range(1, length(lower(text)) - 3)) i FROM documents) WHERE length(lower(text)) >= 5"
COARSE = "SELECT vec_id id, CAST(i - 1 AS VARCHAR) || ':' || CAST(CAST(floor(CAST(x AS DOUBLE) / 0.1) AS BIGINT) AS VARCHAR) token FROM (SELECT vec_id, unnest(embedding) x, generate_subscripts(embedding, 1) i FROM embeddings)"
FAMILIES = {"documents": sets(), "shingles": shingles_sql(), "characters": CHARS, "lineitem": LINE_SETS, "baskets": BASKETS, "events": PROFILES, "pages": sets(PAGES, "page_id", "t"), "embeddings": COARSE}


def statistics(s, d):
    """Rows, distinct tokens, tokens a row and mean cosine of pairs of 100 random rows, of each set family."""
    out = None
    for name, rows in set_families(s, d).items():
        flat = rows.select("id", F.explode("tokens").alias("token")).agg(F.count_distinct("id").alias("rows"), F.count_distinct("token").alias("vocabulary"), F.count("*").alias("nonzeros"))
        one = flat.crossJoin(measures.random_pair_similarity(rows, 100)).select(F.lit(name).alias("family"), "rows", "vocabulary", "nonzeros", "mean_cosine")
        out = one if out is None else out.unionByName(one)
    return out


def statistics_sql(name, set_sql):
    few = Build(set_sql).asked(100).add("sampled", "SELECT id, token, count(*) OVER (PARTITION BY id) n FROM sets WHERE id IN (SELECT query_id FROM asked)")
    few.add("cosines", "SELECT count(*) / sqrt(CAST(any_value(a.n) * any_value(b.n) AS DOUBLE)) c FROM sampled a JOIN sampled b ON a.token = b.token AND a.id < b.id GROUP BY a.id, b.id")
    pairs = "(SELECT count(*) * (count(*) - 1) / 2.0::DOUBLE FROM asked)"
    return few.select(f"SELECT '{name}' family, count(DISTINCT id) AS rows, count(DISTINCT token) vocabulary, count(*) nonzeros, round((SELECT coalesce(sum(c), 0) FROM cosines) / {pairs}, 6) mean_cosine FROM sets")


add("w01_statistics", union_all([statistics_sql(n, q) for n, q in FAMILIES.items()]))(statistics)


#: Share of an item's shingles that a document holds when the item counts as found in it.
HELD = 0.8


def held_shingles(s, d):
    """(item_id, doc_id, hits, held): shingles of an item that a document holds, and their share of the item's."""
    bench = features.token_sets(load(s, d, "benchmark"), "item_id", "text", "shingle")
    items = bench.select(F.col("id").alias("item_id"), F.size("tokens").alias("n"), F.explode("tokens").alias("token"))
    docs = doc_sets(s, d, "shingle").select(F.col("id").alias("doc_id"), F.explode("tokens").alias("token"))
    return items.join(docs, "token").groupBy("item_id", "doc_id").agg(F.count("*").alias("hits"), F.first("n").alias("n")).select("item_id", "doc_id", "hits", (F.col("hits") / F.col("n")).alias("held"))


def contamination(s, d):
    """Benchmark passages in documents: every document that holds most three-word shingles of an item."""
    return held_shingles(s, d).where(F.col("held") >= HELD).withColumn("held", F.round("held", 6))


ITEMS = Build(shingles_sql()).add("items", shingles_sql(3, "benchmark", "item_id")).add("held", "SELECT i.id item_id, s.id doc_id, count(*) hits, count(*) / CAST(any_value(z.n) AS DOUBLE) held FROM items i JOIN sets s USING (token) JOIN (SELECT id, count(*) n FROM items GROUP BY id) z ON z.id = i.id GROUP BY ALL")
add("w14_contamination", ITEMS.select(f"SELECT item_id, doc_id, hits, round(held, 6) held FROM held WHERE held >= {HELD}"))(contamination)


def best_document(s, d):
    """The document that holds most of each item, whatever its share."""
    return top_by(held_shingles(s, d).select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("id"), F.col("held").alias("similarity")), 1)


add("w14_best_document", ITEMS.select('SELECT item_id query_id, CAST(row_number() OVER (PARTITION BY item_id ORDER BY round(held, 9) DESC, doc_id) AS INTEGER) AS "rank", doc_id id, round(held, 6) similarity FROM held QUALIFY "rank" = 1'))(best_document)
