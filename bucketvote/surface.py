"""What users of the search need around it: sources, joins, aggregates, windows, functions, and the SQL surface."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .catalogue import DEPTH, K, NODES, TABLES, WIDTH, asked, buckets, cells, doc_sets
from .functions import features, hashing
from .operators import counters
from .operators import search as S
from .oracle import LINE_SETS, Build, num, sets
from .registry import add
from .sources import tables
from .sources.shared import shared_folder
from .sources.tables import load

# sources and sinks
ALL = " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) n FROM {t}" for t in tables.TABLES)


def table_sizes(s, d):
    out = None
    for t in tables.TABLES:
        one = load(s, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


add("o01_tables", ALL)(table_sizes)


def through(kind):
    def run(s, d):
        path = shared_folder(s, kind)
        rows = load(s, d, "customer").select("c_custkey", "c_name", "c_mktsegment")
        tables.write(rows, path, kind)
        return tables.read(s, path, kind, rows.schema)

    return run


for _kind in ("csv", "json", "orc"):
    add(f"o02_{_kind}", "SELECT c_custkey, c_name, c_mktsegment FROM customer")(through(_kind))


def stored_index(s, d):
    path = shared_folder(s, "index")
    made = cells(s, d)
    tables.save_index(made, path)
    return tables.load_index(s, path, made.schema)


CELL_COLS = 'table_id, bucket_key, node, "row", col, total, cand, votes'
add("x08_stored_index", Build().buckets(K, TABLES, NODES).cells(DEPTH, WIDTH).select(f"SELECT {CELL_COLS} FROM cells"))(stored_index)

# filters, joins
add("o04_filters", "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus LIKE 'F%' AND l_discount IS NOT NULL")(
    lambda s, d: load(s, d, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").like("F%") & F.col("l_discount").isNotNull()).select("l_orderkey", "l_partkey", "l_quantity")
)
ENGLISH = "(SELECT * FROM documents WHERE lang = 'en')"
HITS = 'SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) AS INTEGER) AS "rank", id, hits votes, hits AS upper FROM counts WHERE query_id <> id QUALIFY "rank" <= 10'


def english(s, d):
    return features.token_sets(load(s, d, "documents").where("lang = 'en'"), "doc_id", "text")


add("o05_filter_before_search", Build(sets(ENGLISH)).buckets(K, TABLES, NODES).queries().counts().select(HITS))(lambda s, d: S.search(english(s, d), asked(english(s, d)), K, TABLES, 10, NODES, "exact"))
add("o05_filter_after_search", Build().buckets(K, TABLES, NODES).queries().counts().add("a", HITS).select("SELECT a.* FROM a JOIN documents ON doc_id = id WHERE lang = 'en'"))(
    lambda s, d: S.search(doc_sets(s, d), asked(doc_sets(s, d)), K, TABLES, 10, NODES, "exact").join(load(s, d, "documents").where("lang = 'en'").select(F.col("doc_id").alias("id")), "id", "left_semi")
)


def nation_orders(hint):
    def run(s, d):
        c = load(s, d, "customer").select("c_custkey", "c_nationkey")
        o = load(s, d, "orders").select("o_custkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
        both = o.join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey"))
        per = both.groupBy("c_nationkey").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
        return per.join(load(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("n_name", "n", "cents")

    return run


for _hint in ("broadcast", "merge", "shuffle_hash"):
    add(f"o06_join_{_hint}", "SELECT n_name, count(*) n, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) cents FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")(nation_orders(_hint))
for _how, _sql in {"left_semi": "SEMI", "left_anti": "ANTI"}.items():
    add(f"o07_{_how}", f"SELECT doc_id, lang FROM documents {_sql} JOIN labels USING (doc_id)")(lambda s, d, h=_how: load(s, d, "documents").join(load(s, d, "labels"), "doc_id", h).select("doc_id", "lang"))
for _how in ("left", "full"):
    add(f"o07_{_how}", f"SELECT doc_id, lang, coalesce(quality, -1) quality FROM documents {_how} JOIN labels USING (doc_id)")(lambda s, d, h=_how: load(s, d, "documents").join(load(s, d, "labels"), "doc_id", h).select("doc_id", "lang", F.coalesce("quality", F.lit(-1)).alias("quality")))
add("o08_theta_join", "SELECT a.n_name AS left_name, b.n_name AS right_name FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(
    lambda s, d: load(s, d, "nation").alias("a").join(load(s, d, "nation").alias("b"), F.expr("a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("left_name"), F.col("b.n_name").alias("right_name"))
)


def size_range(s, d, least=0.8):
    """Per asked set, how many have a size that allows similarity `least`: an equi join on logarithmic size bands, then the exact test."""
    rows = doc_sets(s, d).select("id", F.size("tokens").alias("n"))
    band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(1 / least))).cast("int")
    sized = rows.withColumn("band", band)
    q = asked(sized).select(F.col("id").alias("query_id"), F.col("n").alias("nq"), F.explode(F.expr("array(band - 1, band, band + 1)")).alias("band"))
    return q.join(sized, "band").where((F.col("query_id") != F.col("id")) & (F.col("n") * 5 >= F.col("nq") * 4) & (F.col("nq") * 5 >= F.col("n") * 4)).groupBy("query_id").agg(F.count("*").alias("near_size"))


add("o09_range_join", Build().add("z", "SELECT id, count(*) n FROM sets GROUP BY id").select(f"SELECT a.id query_id, count(*) near_size FROM z a JOIN z b ON a.id <> b.id AND b.n * 5 >= a.n * 4 AND a.n * 5 >= b.n * 4 WHERE a.id % 100 = 0 GROUP BY 1"))(size_range)


def as_of(s, d):
    """Each purchase with the user's latest view before it: one sort per user, no join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return load(s, d, "events").withColumn("view_id", seen).where("event_type = 'purchase'").select("event_id", F.coalesce("view_id", F.lit(-1)).alias("view_id"))


add("o10_as_of", "SELECT event_id, coalesce(view_id, -1) view_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) view_id FROM events) WHERE event_type = 'purchase'")(as_of)


def within_hour(s, d):
    """Events of a user within an hour after an error: an equi join on hours, the error in two of them."""
    e = load(s, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = F.floor(F.col("t") / 3_600_000_000)
    errors = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("t").alias("t0"), F.explode(F.array(hour, hour + 1)).alias("h"))
    return errors.join(e.withColumn("h", hour), ["user_id", "h"]).where("t > t0 and t <= t0 + 3600000000").select("error_id", "event_id")


add("o10_interval_join", "SELECT a.event_id error_id, b.event_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error'")(within_hour)

# aggregates
add("o11_aggregates", "SELECT source, count(*) n, count(DISTINCT lang) langs, max(n_chars) longest, CAST(sum(n_chars) AS BIGINT) chars, round(quantile_cont(n_chars, 0.5), 6) median, max({n: n_chars, d: doc_id}).d longest_id FROM documents GROUP BY source")(
    lambda s, d: load(s, d, "documents").groupBy("source").agg(F.count("*").alias("n"), F.count_distinct("lang").alias("langs"), F.max("n_chars").alias("longest"), F.sum("n_chars").alias("chars"), F.round(F.percentile("n_chars", 0.5), 6).alias("median"), F.max(F.struct("n_chars", "doc_id"))["doc_id"].alias("longest_id"))
)
for _how in ("rollup", "cube"):
    add(f"o12_{_how}", f"SELECT lang, source, count(*) n, CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS level FROM documents GROUP BY {_how}(lang, source)")(lambda s, d, h=_how: getattr(load(s, d, "documents"), h)("lang", "source").agg(F.count("*").alias("n"), F.grouping_id().alias("level")))
add("o12_grouping_sets", "SELECT lang, source, count(*) n FROM documents GROUP BY GROUPING SETS ((lang), (source))")(lambda s, d: load(s, d, "documents").groupingSets([[F.col("lang")], [F.col("source")]], "lang", "source").agg(F.count("*").alias("n")))
KINDS = ["click", "error", "purchase", "signup", "view"]
PIVOT = "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS \"{k}\"" for k in KINDS) + " FROM events GROUP BY user_id"


def pivoted(s, d):
    return load(s, d, "events").groupBy("user_id").pivot("event_type", KINDS).count().na.fill(0)


add("o13_pivot", PIVOT)(pivoted)
add("o13_unpivot", " UNION ALL ".join(f"SELECT user_id, '{k}' AS kind, \"{k}\" n FROM ({PIVOT})" for k in KINDS))(lambda s, d: pivoted(s, d).unpivot("user_id", KINDS, "kind", "n"))

# windows, sorts, sets, samples


def ranks(s, d):
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    rank = {"rn": F.row_number(), "r": F.rank(), "dr": F.dense_rank(), "fourth": F.ntile(4)}
    share = {"pr": F.percent_rank(), "cd": F.cume_dist()}
    return load(s, d, "orders").select("o_orderkey", *[f.over(w).alias(n) for n, f in rank.items()], *[F.round(f.over(w), 6).alias(n) for n, f in share.items()])


add("o14_ranks", "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) rn, CAST(rank() OVER w AS INTEGER) r, CAST(dense_rank() OVER w AS INTEGER) dr, CAST(ntile(4) OVER w AS INTEGER) fourth, round(percent_rank() OVER w, 6) pr, round(cume_dist() OVER w, 6) cd FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey)")(ranks)


def neighbours(s, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    near = {"before": F.lag("event_type").over(w), "after": F.lead("event_type").over(w), "last3": F.count("*").over(w.rowsBetween(-2, 0)), "near": F.count("*").over(w.rangeBetween(-100, 0))}
    return load(s, d, "events").select("event_id", *[c.alias(n) for n, c in near.items()])


add("o15_analytic", "SELECT event_id, lag(event_type) OVER w before, lead(event_type) OVER w after, count(*) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) last3, count(*) OVER (w RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) near FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")(neighbours)
add("o16_top", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC NULLS LAST, doc_id LIMIT 50 OFFSET 10")(lambda s, d: load(s, d, "documents").select("doc_id", "n_chars").orderBy(F.desc_nulls_last("n_chars"), "doc_id").offset(10).limit(50))
add("o16_top_per_key", "SELECT lang, doc_id, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) <= 5")(
    lambda s, d: load(s, d, "documents").select("lang", "doc_id", "n_chars").withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id"))).where("r <= 5").drop("r")
)
_LINES, _PARTS = "SELECT l_partkey AS part FROM lineitem", "SELECT p_partkey AS part FROM part WHERE p_size < 20"
for _op, _sql in {"intersect": "INTERSECT", "intersectAll": "INTERSECT ALL", "subtract": "EXCEPT", "exceptAll": "EXCEPT ALL", "unionAll": "UNION ALL"}.items():
    add(f"o17_{_op.lower()}", f"{_LINES} {_sql} {_PARTS}")(lambda s, d, o=_op: getattr(load(s, d, "lineitem").select(F.col("l_partkey").alias("part")), o)(load(s, d, "part").where("p_size < 20").select(F.col("p_partkey").alias("part"))))
add("o18_hash_sample", f"SELECT event_id FROM events WHERE {num('event_id')} % 10 = 0")(lambda s, d: load(s, d, "events").where(hashing.token_number(F.col("event_id")) % 10 == 0).select("event_id"))
add("o18_bottom_k", f"SELECT lang, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY {num('doc_id')}, doc_id) <= 20")(
    lambda s, d: load(s, d, "documents").select("lang", "doc_id").withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(hashing.token_number(F.col("doc_id")), "doc_id"))).where("r <= 20").drop("r")
)

# functions
add("o19_strings", "SELECT p_partkey, upper(trim(p_name)) u, regexp_replace(p_brand, '[^0-9]', '', 'g') digits, concat_ws('/', p_brand, p_type) joined, length(p_name) n, CAST(levenshtein(p_name, p_type) AS INTEGER) lev FROM part")(
    lambda s, d: load(s, d, "part").select("p_partkey", F.upper(F.trim("p_name")).alias("u"), F.regexp_replace("p_brand", "[^0-9]", "").alias("digits"), F.concat_ws("/", "p_brand", "p_type").alias("joined"), F.length("p_name").alias("n"), F.levenshtein("p_name", "p_type").alias("lev"))
)
add("o20_dates", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) y, CAST(month(o_orderdate) AS INTEGER) m, strftime(date_trunc('quarter', o_orderdate), '%Y-%m-%d') q, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) age, strftime(CAST(o_orderdate AS DATE) + 30, '%Y-%m-%d') due FROM orders")(
    lambda s, d: load(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format(F.date_trunc("quarter", "o_orderdate"), "yyyy-MM-dd").alias("q"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("age"), F.date_format(F.date_add(F.to_date("o_orderdate"), 30), "yyyy-MM-dd").alias("due"))
)
add("o21_math", f"SELECT p_partkey, CAST(bit_count({num('p_name')}) AS INTEGER) ones, {num('p_name')} >> 4 high, round(ln(p_retailprice), 6) l, round(sqrt(p_size), 6) r, lower(hex(p_partkey)) h FROM part")(
    lambda s, d: load(s, d, "part").withColumn("x", hashing.token_number(F.col("p_name"))).select("p_partkey", F.bit_count("x").alias("ones"), F.shiftright("x", 4).alias("high"), F.round(F.log("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_size"), 6).alias("r"), F.lower(F.hex("p_partkey")).alias("h"))
)
add("o22_arrays", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) positive, list_position(embedding, list_max(embedding)) AS top_at, round(list_sum(list_transform(embedding[1:8], lambda x: CAST(x AS DOUBLE) * x)), 6) head FROM embeddings")(
    lambda s, d: load(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.array_position("embedding", F.array_max("embedding")).alias("top_at"), F.round(F.aggregate(F.slice("embedding", 1, 8), F.lit(0.0), lambda a, x: a + x.cast("double") * x), 6).alias("head"))
)
add("o23_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))
add("o24_conditional", "SELECT doc_id, coalesce(quality, -1) q, CASE WHEN toxic = 1 THEN 'bad' WHEN toxic = 0 THEN 'good' ELSE 'unknown' END verdict, coalesce(nullif(quality, 0), -1) nq, greatest(coalesce(quality, 0), coalesce(toxic, 0)) g FROM documents LEFT JOIN labels USING (doc_id)")(
    lambda s, d: load(s, d, "documents").join(load(s, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.when(F.col("toxic") == 1, "bad").when(F.col("toxic") == 0, "good").otherwise("unknown").alias("verdict"), F.coalesce(F.nullif("quality", F.lit(0)), F.lit(-1)).alias("nq"), F.greatest(F.coalesce("quality", F.lit(0)), F.coalesce("toxic", F.lit(0))).alias("g"))
)
SUBQUERY = """WITH big AS (SELECT o_custkey, max(o_totalprice) top FROM orders GROUP BY o_custkey)
  SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM big b WHERE b.o_custkey = c.c_custkey AND b.top > (SELECT avg(top) FROM big))
  AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey < 3)"""


def by_sql(s, d):
    for t in ("orders", "customer", "nation"):
        load(s, d, t).createOrReplaceTempView(t)
    return s.sql(SUBQUERY)


add("o25_subqueries", SUBQUERY)(by_sql)


# user functions
def arrow_distance(s, d):
    """Jaccard by an Arrow function: checked against the built-in expression, which the engine uses."""

    @F.pandas_udf("double")
    def jac(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([len(set(x) & set(y)) / max(1, len(set(x) | set(y))) for x, y in zip(a, b)])

    rows = doc_sets(s, d)
    top = S.brute_force(rows, asked(rows), 3, "jaccard").drop("similarity")
    both = top.join(rows.withColumnRenamed("tokens", "x"), "id").join(rows.select(F.col("id").alias("query_id"), F.col("tokens").alias("y")), "query_id")
    return both.select("query_id", "id", F.round(jac("x", "y"), 6).alias("similarity"))


JAC = "shared / CAST(na + nb - shared AS DOUBLE)"
add("o27_arrow_function", Build().asked().pairs().select(f"SELECT query_id, id, round({JAC}, 6) similarity FROM sim_rows QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round({JAC}, 9) DESC, id) <= 3"))(arrow_distance)


def table_function(s, d):
    """Keys of a text as a table function, for SQL users."""
    from .functions.udtf import lsh_keys

    s.udtf.register("lsh_keys", lsh_keys)
    load(s, d, "documents").createOrReplaceTempView("documents")
    return s.sql(f"SELECT d.doc_id id, k.table_id, k.bucket_key FROM documents d, LATERAL lsh_keys(d.text, {K}, {TABLES}) k")


add("o29_table_function", Build().signature(K * TABLES).dense(K * TABLES).keys(K, TABLES).select("SELECT id, table_id, bucket_key FROM keys"))(table_function)


def event_ids(s, d):
    return load(s, d, "events").where("user_id is not null").select("event_type", F.col("user_id").alias("id"))


add("s11_lossy_counting")(lambda s, d: counters.lossy_counting(event_ids(s, d), "event_type", 0.02))
add("s09_counters")(lambda s, d: counters.frequent_counters(event_ids(s, d), "event_type", 20))
add("a05_packed_merge", Build().buckets(K, TABLES, NODES).cells(DEPTH, WIDTH).queries().local().merge("merged", "local_cells", "query_id").select('SELECT query_id, "row", col, total, cand, votes FROM merged'))(
    lambda s, d: counters.packed_merge(S.local_merge(S.hash_queries(asked(doc_sets(s, d)), K, TABLES), cells(s, d)), ["query_id"])
)


def mergeability(s, d, k=10):
    """How many of the true top k (id, count) per type the merge of per-node top-k lists gets wrong."""
    rows = load(s, d, "events").where("user_id is not null").select("event_type", F.col("user_id").alias("id"), (hashing.token_number(F.col("event_id")) % 4).cast("int").alias("node"))

    def best(counts, keys):
        w = Window.partitionBy(*keys).orderBy(F.desc("n"), "id")
        return counts.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).drop("r")

    true = best(rows.groupBy("event_type", "id").agg(F.count("*").alias("n")), ["event_type"])
    lists = best(rows.groupBy("event_type", "node", "id").agg(F.count("*").alias("n")), ["event_type", "node"])
    merged = best(lists.groupBy("event_type", "id").agg(F.sum("n").alias("n")), ["event_type"])
    return true.select("event_type", "id", "n").exceptAll(merged.select("event_type", "id", "n")).groupBy("event_type").agg(F.count("*").alias("lost_or_undercounted"))


MERGE = f"""WITH e AS (SELECT event_type, user_id id, {num('event_id')} % 4 node FROM events WHERE user_id IS NOT NULL),
  t AS (SELECT * FROM (SELECT event_type, id, count(*) n FROM e GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY event_type ORDER BY n DESC, id) <= 10),
  l AS (SELECT * FROM (SELECT event_type, node, id, count(*) n FROM e GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY event_type, node ORDER BY n DESC, id) <= 10),
  m AS (SELECT * FROM (SELECT event_type, id, CAST(sum(n) AS BIGINT) n FROM l GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY event_type ORDER BY n DESC, id) <= 10)
  SELECT event_type, count(*) lost_or_undercounted FROM (SELECT * FROM t EXCEPT SELECT * FROM m) GROUP BY 1"""
add("s13_mergeability", MERGE)(mergeability)
add("s08_builtin_count_min")(lambda s, d: event_ids(s, d).groupBy("event_type").agg(F.count_min_sketch("id", F.lit(0.05), F.lit(0.95), F.lit(1)).alias("packed")).select("event_type", F.length("packed").alias("bytes")))
