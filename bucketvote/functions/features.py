"""From tables to sets: rows (id, tokens) with distinct tokens, or (id, token, weight)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def once(value: Column, body) -> Column:
    """body(value), value bound to a name: inside a lambda an expression would be made anew for every element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def word_line(text: Column) -> Column:
    """Words of ASCII letters and digits of the lower-cased text, in order, with a blank between."""
    return F.trim(F.regexp_replace(F.lower(text), "[^a-z0-9]+", " "))


def words(text: Column) -> Column:
    """The words of `word_line`; null where there are none."""
    return F.filter(F.split(word_line(text), " "), lambda w: w != "")


def grams(items: Column, n: int) -> Column:
    """Runs of n words; a shorter text is one run."""
    return F.when(F.size(items) >= n, F.transform(F.sequence(F.lit(1), F.size(items) - n + 1), lambda i: F.array_join(F.slice(items, i, n), " "))).otherwise(F.array(F.array_join(items, " ")))


def token_sets(df: DataFrame, id_col: str, text_col: str, mode: str = "word", n: int = 3) -> DataFrame:
    """(id, tokens). Texts without a token have no row: they have no signature."""
    if mode not in ("word", "shingle", "char"):
        raise ValueError(mode)
    items = F.split(F.lower(F.col(text_col)), "") if mode == "char" else words(F.col(text_col))
    rows = df.where(F.col(text_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), items.alias("_items"))
    if mode == "word":
        t = F.col("_items")
    elif mode == "shingle":
        t = once(F.col("_items"), lambda w: F.when(F.size(w) > 0, grams(w, n)))
    else:
        t = once(F.col("_items"), lambda w: F.when(F.size(w) >= n, F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: F.concat(*[F.get(w, i + j) for j in range(n)]))))
    return rows.select("id", F.array_distinct(t).alias("tokens")).where(F.size("tokens") > 0)


LINE_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate", "l_extendedprice")


def line_id() -> Column:
    """56 bits of md5 over the columns that identify a lineitem row."""
    parts = [F.date_format(c, "yyyy-MM-dd") if c == "l_shipdate" else F.round(F.col(c) * 100).cast("long").cast("string") if c == "l_extendedprice" else F.col(c).cast("string") for c in LINE_KEY]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 14), 16, 10).cast("long")


def line_values() -> list[Column]:
    whole = {"l_quantity": 1, "l_discount": 100, "l_tax": 100}
    out = [F.concat(F.lit(f"{c[2:]}="), F.col(c).cast("string")) for c in ("l_partkey", "l_suppkey", "l_returnflag", "l_linestatus")]
    out += [F.concat(F.lit(f"{c[2:]}="), F.round(F.col(c) * s).cast("long").cast("string")) for c, s in whole.items()]
    return [*out, F.concat(F.lit("month="), F.date_format("l_shipdate", "yyyy-MM"))]


def line_rows(lineitem: DataFrame) -> DataFrame:
    """Categorical rows of eight attributes as sets."""
    return lineitem.select(line_id().alias("id"), F.array_distinct(F.array(*line_values())).alias("tokens"))


def hash_features(df: DataFrame, id_cols: Column, values: list[Column], dims: int = 1 << 20) -> DataFrame:
    """(id, idx): positions of hashed values below dims."""
    from .hashing import token_number

    return df.select(id_cols.alias("id"), F.array_sort(F.array_distinct(F.transform(F.array(*values), lambda t: token_number(t) % dims))).alias("idx"))


def baskets(orders: DataFrame, lineitem: DataFrame) -> DataFrame:
    lines = lineitem.select("l_orderkey", "l_partkey").join(orders.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return lines.groupBy(F.col("o_custkey").alias("id")).agg(F.collect_set(F.col("l_partkey").cast("string")).alias("tokens"))


def event_profiles(events: DataFrame) -> DataFrame:
    token = F.concat("event_type", F.lit(":"), F.coalesce(F.get_json_object("props", "$.k"), F.lit("")))
    return events.where("user_id is not null").groupBy(F.col("user_id").alias("id")).agg(F.collect_set(token).alias("tokens"))


def weighted_vectors(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, token, weight): word counts. Counting is per row, before any shuffle moves a token."""
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.explode(words(F.col(text_col))).alias("token"))
    return rows.groupBy("id", "token").agg(F.count("*").alias("weight"))


def binarise(vectors: DataFrame) -> DataFrame:
    return vectors.where("weight <> 0").select("id", "token")


def vector_norms(vectors: DataFrame) -> DataFrame:
    return vectors.groupBy("id").agg(F.sqrt(F.sum(F.col("weight") * F.col("weight"))).alias("norm"), F.count("*").alias("size"))


def page_text(html: Column) -> Column:
    """Text of a page: scripts and styles go with their content, other tags leave a space."""
    t = F.regexp_replace(F.lower(html), "<script[^>]*>.*?</script>", " ")
    t = F.regexp_replace(t, "<style[^>]*>.*?</style>", " ")
    return F.regexp_replace(t, "<[^>]*>", " ")


def quantise_dense(df: DataFrame, id_col: str, vec_col: str, width: float = 0.1) -> DataFrame:
    """Dense components as tokens `position:bin`."""
    t = F.transform(F.col(vec_col), lambda x, i: F.concat(i.cast("string"), F.lit(":"), F.floor(x.cast("double") / width).cast("string")))
    return df.where(F.col(vec_col).isNotNull()).select(F.col(id_col).alias("id"), t.alias("tokens"))


def to_ml_vector(sets: DataFrame, dims: int = 1 << 20) -> DataFrame:
    from pyspark.ml.feature import HashingTF

    return HashingTF(numFeatures=dims, binary=True, inputCol="tokens", outputCol="features").transform(sets)
