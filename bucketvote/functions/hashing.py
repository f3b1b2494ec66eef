"""Hash families shared by seed, set signatures, and table keys. The portable family agrees with DuckDB bit for bit."""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1
#: Added per bin of distance to borrowed values, so that two borrowed values agree only over equal distances.
OFFSET = 1_000_003


def hash_coefficients(seed: int, count: int) -> list[tuple[int, int]]:
    rng = random.Random(seed)
    return [(rng.randrange(1, PRIME), rng.randrange(PRIME)) for _ in range(count)]


def token_number(token: Column) -> Column:
    """28 bits of md5."""
    return F.conv(F.substring(F.md5(token.cast("string")), 1, 7), 16, 10).cast("long")


def universal(number: Column, a: int, b: int) -> Column:
    return (number * F.lit(a).cast("long") + F.lit(b).cast("long")) % F.lit(PRIME).cast("long")


def hash_column(token: Column, hash_no: int, family: str = "portable", seed: int = 1) -> Column:
    if family == "fast":
        return F.xxhash64(F.lit(seed), F.lit(hash_no), token)
    a, b = hash_coefficients(seed, hash_no + 1)[hash_no]
    return universal(token_number(token), a, b)


def minhash(sets: DataFrame, hashes: int, seed: int = 1) -> DataFrame:
    """(id, sig): the least hash of each of many families; one pass over the row, no shuffle."""
    co = hash_coefficients(seed, hashes)
    numbers = sets.select("id", F.transform("tokens", token_number).alias("x"))
    return numbers.select("id", F.array(*[F.array_min(F.expr(f"transform(x, v -> (v * {a}L + {b}L) % {PRIME}L)")) for a, b in co]).alias("sig"))


def one_permutation(sets: DataFrame, bins: int, seed: int = 1) -> DataFrame:
    """(id, sig): bins of one hash, each with its least value or null.

    A bin is a range of hash values: in the sorted hashes the first of each bin is its least, so one sort of the row's
    own tokens does; nothing is exploded or shuffled.
    """
    a, b = hash_coefficients(seed, 1)[0]
    u = sets.select("id", F.array_sort(F.array_distinct(F.transform("tokens", lambda t: universal(token_number(t), a, b)))).alias("u"))
    # what a lambda uses more than once is bound by an outer one, or it would be made anew for every element
    firsts = u.select("id", F.expr(f"transform(array(u), w -> filter(w, (v, i) -> i = 0 or cast(v * {bins} div {PRIME} as int) <> cast(get(w, i - 1) * {bins} div {PRIME} as int)))[0]").alias("f"))
    place = f"transform(array(f), g -> transform(array(transform(g, v -> cast(v * {bins} div {PRIME} as int))), p -> transform(sequence(0, {bins - 1}), i -> element_at(g, nullif(cast(array_position(p, i) as int), 0))))[0])[0]"
    return firsts.select("id", F.expr(place).alias("sig"))


def coins(bins: int, seed: int) -> list[int]:
    rng = random.Random(seed * 7919 + bins)
    return [rng.randrange(2) for _ in range(bins)]


def densify(signed: DataFrame, bins: int, seed: int = 1, coin: str = "per_bin", offset: bool = False, wrap: bool = True) -> DataFrame:
    """Fills empty bins from the nearest full bin: `per_bin` by a coin of (seed, bin), `always_right`, or `closest_side` with the coin for ties."""
    toss = "array(" + ", ".join(map(str, coins(bins, seed))) + ")"
    after, before = "get(filter(full, j -> j > i), 0)", "try_element_at(filter(full, j -> j < i), -1)"
    first, last = "full[0]", "element_at(full, -1)"
    right = f"coalesce({after}, {first if wrap else last})"
    left = f"coalesce({before}, {last if wrap else first})"
    go_right, go_left = f"pmod({right} - i, {bins})", f"pmod(i - {left}, {bins})"
    if not wrap:
        go_right, go_left = f"abs({right} - i)", f"abs(i - {left})"
    pick = {"per_bin": "coin[i] = 1", "always_right": "true", "closest_side": f"{go_right} < {go_left} or ({go_right} = {go_left} and coin[i] = 1)"}[coin]
    far = f"if({pick}, {go_right}, {go_left})"
    value = f"s[if({pick}, {right}, {left})]" + (f" + {far} * {OFFSET}" if offset else "")
    fill = f"transform(sequence(0, {bins - 1}), i -> coalesce(s[i], {value}))"
    bound = f"transform(array(sig), s -> transform(array(filter(sequence(0, {bins - 1}), i -> s[i] is not null)), full -> transform(array({toss}), coin -> {fill})[0])[0])[0]"
    return signed.select("id", F.expr(bound).alias("sig"))


def _table_keys(k: int, tables: int, layout: str) -> str:
    parts = f"slice(s, t * {k} + 1, {k})" if layout == "block" else f"transform(sequence(0, {k - 1}), j -> s[t + j * {tables}])"
    return f"transform(array(sig), s -> transform(sequence(0, {tables - 1}), t -> concat_ws('-', transform({parts}, v -> cast(v as string)))))[0]"


def bucket_keys(signed: DataFrame, k: int, tables: int, layout: str = "block") -> DataFrame:
    """(id, table_id, bucket_key): K values of each table, joined."""
    return signed.select("id", F.posexplode(F.expr(_table_keys(k, tables, layout))).alias("table_id", "bucket_key"))


def signatures(sets: DataFrame, bins: int, seed: int = 1, family: str = "one_permutation", **options) -> DataFrame:
    """(id, sig): MinHash, or one permutation with its empty bins filled."""
    return minhash(sets, bins, seed) if family == "minhash" else densify(one_permutation(sets, bins, seed), bins, seed, **options)


def keys_of(sets: DataFrame, k: int, tables: int, seed: int = 1, family: str = "one_permutation", **options) -> DataFrame:
    layout = options.pop("layout", "block")
    return bucket_keys(signatures(sets, k * tables, seed, family, **options), k, tables, layout)


def beside_tokens(sets: DataFrame, make) -> DataFrame:
    """(id, tokens, made column): make turns (id, tokens) into (id, column); its id carries the row's tokens along, so nothing is joined."""
    made = make(sets.select(F.struct("id", "tokens").alias("id"), "tokens"))
    return made.select("id.id", "id.tokens", *[c for c in made.columns if c != "id"])


def key_lists(sets: DataFrame, k: int, tables: int, seed: int = 1, family: str = "one_permutation", **options) -> DataFrame:
    """(id, tokens, keys): a row's keys of all tables in a list, each with its table."""
    layout = options.pop("layout", "block")
    made = beside_tokens(sets, lambda rows: signatures(rows, k * tables, seed, family, **options))
    return made.select("id", "tokens", F.expr(f"transform({_table_keys(k, tables, layout)}, (b, i) -> concat(i, ':', b))").alias("keys"))


def jaccard_estimate(a: Column, b: Column) -> Column:
    same = F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)
    return same / F.size(a)


def directions(bits: int, dims: int, seed: int = 1) -> list[list[float]]:
    rng = random.Random(seed)
    return [[rng.gauss(0, 1) for _ in range(dims)] for _ in range(bits)]


def signed_projection(df: DataFrame, id_col: str, vec_col: str, bits: int, dims: int, seed: int = 1) -> DataFrame:
    """(id, sig): signs of random projections of dense vectors."""
    dot = [F.aggregate(F.zip_with(F.col(vec_col), F.array(*[F.lit(x) for x in r]), lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, x: s + x) for r in directions(bits, dims, seed)]
    return df.where(F.col(vec_col).isNotNull()).select(F.col(id_col).alias("id"), F.array(*[(d >= 0).cast("long") for d in dot]).alias("sig"))
