"""Closed forms of the method's parameters, as expressions over small relations."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import token_number

#: K and L of the experiments, and two of our own for short rows.
SETTINGS = ((4, 24), (4, 16), (4, 32), (2, 32), (1, 32))
#: Sensitivities (p1, p2) to choose parameters for.
SENSITIVITIES = ((0.8, 0.3), (0.9, 0.4), (0.7, 0.5))


def collision_curve(lines: DataFrame) -> DataFrame:
    """Probability of one hit at least, and expected hits, at the similarities that lines have to a full one: q units of the 50 make sets of Jaccard similarity q / 50."""
    seen = lines.where("l_quantity is not null").groupBy((F.round("l_quantity") / 50).alias("s")).agg(F.count("*").alias("lines"))
    settings = lines.sparkSession.createDataFrame(list(SETTINGS), "k int, l int")
    pk = F.pow("s", "k")
    # a row a quantity, and the few fixed settings
    return seen.crossJoin(settings).select("k", "l", "s", "lines", F.round(1 - F.pow(1 - pk, "l"), 6).alias("any_hit"), F.round(F.col("l") * pk, 6).alias("expected_hits"))


def sized_cases(orders: DataFrame) -> DataFrame:
    """(o_orderpriority, n, p1, p2, a, b): the orders of each priority as the rows to search, at each pair of sensitivities."""
    n = orders.groupBy("o_orderpriority").agg(F.count("*").alias("n"))
    pairs = orders.sparkSession.createDataFrame(list(SENSITIVITIES), "p1 double, p2 double")
    return n.crossJoin(pairs).withColumns({"a": -F.log("p1"), "b": -F.log("p2")})


def choose_parameters(orders: DataFrame, boost: float = 1.0) -> DataFrame:
    """K, L, the sensitivity ratio a/b and rho = a/(b-a) for each case, and whether the instance is strong."""
    base = sized_cases(orders)
    rho = F.col("a") / (F.col("b") - F.col("a"))
    k = F.log(F.col("n").cast("double")) / (F.col("b") - F.col("a"))
    return base.select("o_orderpriority", "n", "p1", "p2", F.round(F.col("a") / F.col("b"), 6).alias("ratio"), F.round(rho, 6).alias("rho"), F.round(k, 6).alias("k"), F.round(F.pow(F.col("n").cast("double"), rho) * boost, 4).alias("l"), (F.col("a") / F.col("b") < 0.5).alias("strong"))


def theorem_setting(n: int, p1: float, p2: float) -> tuple[int, int]:
    """Whole K and L of the closed forms, for n rows and sensitivities p1, p2."""
    gap = math.log(p1) - math.log(p2)
    return math.ceil(math.log(n) / gap), math.ceil(n ** (-math.log(p1) / gap))


def signal_to_noise(orders: DataFrame) -> DataFrame:
    p = choose_parameters(orders)
    return p.select("o_orderpriority", "n", "p1", "p2", F.round(F.col("l") * F.pow("p1", "k"), 3).alias("near_signal"), F.round(F.col("n") * F.col("l") * F.pow("p2", "k") / F.col("l"), 3).alias("far_per_table"))


def cost_model(orders: DataFrame) -> DataFrame:
    """Merges and depth of a query by strategy, for 32 tables, over the nodes that orders dealt to 2 to 20 nodes reach; and the rows of the fullest."""
    dealt = orders.select(token_number(F.col("o_orderkey")).alias("x"), F.explode(F.array(*[F.lit(m) for m in (2, 4, 8, 16, 20)])).alias("dealt"))
    per = dealt.groupBy("dealt", (F.col("x") % F.col("dealt")).alias("node")).agg(F.count("*").alias("n"))
    m = per.groupBy("dealt").agg(F.count("*").alias("m"), F.max("n").alias("most"))
    rounds = F.ceil(F.log2(F.col("m").cast("double"))).cast("long")
    merges = F.col("m") * 32 + F.col("m") - 1
    both = F.explode(F.array(F.struct(F.lit("tree").alias("strategy"), (rounds + 5).alias("depth")), F.struct(F.lit("linear").alias("strategy"), (F.col("m") - 1 + 5).alias("depth"))))
    return m.select("m", "most", merges.alias("merges"), both.alias("way")).select("m", "most", "way.strategy", "merges", "way.depth")


def boost_repetitions(lines: DataFrame) -> DataFrame:
    """How often to repeat a draw of lines until one of a flag is among them, but for a given failure; null where every line has the flag."""
    total = lines.agg(F.count("*").alias("t"))
    share = lines.groupBy("l_returnflag").agg(F.count("*").alias("n")).crossJoin(total).select("l_returnflag", (F.col("n") / F.col("t")).alias("success"))
    base = share.withColumn("failure", F.explode(F.array(*[F.lit(f) for f in (0.1, 0.01, 0.001)])))
    return base.select("l_returnflag", "failure", "success", F.ceil(F.log("failure") / F.log(F.nullif(1 - F.col("success"), F.lit(0.0)))).cast("long").alias("repetitions"))


def dedup_limit(orders: DataFrame) -> DataFrame:
    """As near pairs become equal, rho falls to 0 and one table is enough: for the orders of each priority."""
    base = orders.groupBy("o_orderpriority").agg(F.count("*").alias("n")).withColumn("p1", F.explode(F.array(*[F.lit(p) for p in (0.8, 0.9, 0.99, 0.999)])))
    a = -F.log("p1")
    rho = a / (-F.log(F.lit(0.3)) - a)
    return base.select("o_orderpriority", "n", "p1", F.round(rho, 6).alias("rho"), F.round(F.pow(F.col("n").cast("double"), rho), 4).alias("tables"))


def hash_cost(sets: DataFrame) -> DataFrame:
    """Hashes a token costs, and all tokens of the sets: one per value of the signature, or one for all bins."""
    tokens = sets.agg(F.coalesce(F.sum(F.size("tokens")), F.lit(0)).alias("tokens"))
    cost = sets.sparkSession.createDataFrame(list(SETTINGS), "k int, l int").withColumn("per_minhash", F.col("k") * F.col("l"))
    # a row, and the few fixed settings
    return tokens.crossJoin(cost).select("k", "l", "per_minhash", F.lit(1).alias("per_one_permutation"), (F.col("tokens") * F.col("per_minhash")).alias("all_minhash"), F.col("tokens").alias("all_one_permutation"))


def size_sketch(load: float, f_min: float) -> int:
    """Columns so that a candidate with f_min hits outweighs the rest of its cell on average."""
    return max(1, int(-(-2 * load // max(f_min, 1e-9))))


def sketch_sizes(lines: DataFrame, hits: tuple[int, ...] = (4, 12)) -> DataFrame:
    """(load_ids, hits, suppliers, width) of `size_sketch`, for a bucket a supplier that holds its lines: a row for each number of lines that occurs."""
    loads = lines.groupBy("l_suppkey").agg(F.count("*").alias("load_ids")).groupBy("load_ids").agg(F.count("*").alias("suppliers"))
    each = loads.withColumn("hits", F.explode(F.array(*[F.lit(h) for h in hits])))
    return each.select("load_ids", "hits", "suppliers", F.ceil(2 * F.col("load_ids") / F.col("hits")).cast("int").alias("width"))


def choose_physical(queries: int, tables: int, depth: int, width: int, nodes: int, limit: int = 64 << 20) -> dict[str, str]:
    """Broadcast or shuffled probe, and one-level or tree merge, from sizes alone."""
    keys, cells = queries * tables * 24, queries * depth * width * 24
    return {"probe": "broadcast" if keys <= limit else "shuffle", "merge": "multiway" if cells * nodes <= limit * 16 else "tree"}
