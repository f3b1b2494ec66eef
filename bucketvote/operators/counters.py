"""Counter summaries: frequent items and lossy counts, and a merge of cells as an aggregate function.

Summaries are made in each partition and merged, so no task sees all rows of a key: what is shuffled is bounded by the
counters of a partition.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, hash_coefficients
from .sketch import SEED

SHAPE = "key string, id long, n long, slack long"


def _cut(counts: dict, room: int) -> int:
    """Takes the (room + 1)-th largest count from all and drops what falls to zero; returns what was taken."""
    if len(counts) <= room:
        return 0
    taken = sorted(counts.values(), reverse=True)[room]
    for k in [k for k, v in counts.items() if v <= taken]:
        del counts[k]
    for k in counts:
        counts[k] -= taken
    return taken


def frequent_counters(rows: DataFrame, key: str, counters: int) -> DataFrame:
    """(key, id, n, slack): at most `counters` ids a key; the true count lies in [n, n + slack], and slack is at most rows / (counters + 1)."""

    def summarise(parts: Iterator[pd.DataFrame]):
        held, slack = {}, {}
        for part in parts:
            for (k, i), n in part.groupby(["key", "id"]).size().items():
                held.setdefault(k, {})[int(i)] = held.get(k, {}).get(int(i), 0) + int(n)
            for k, counts in held.items():
                slack[k] = slack.get(k, 0) + _cut(counts, counters)
        yield pd.DataFrame([(k, i, n, slack[k]) for k, c in held.items() for i, n in c.items()], columns=["key", "id", "n", "slack"])

    def merge(one: pd.DataFrame) -> pd.DataFrame:
        counts = one.groupby("id")["n"].sum().astype(int).to_dict()
        slack = int(one.drop_duplicates("part")["slack"].sum()) + _cut(counts, counters)
        return pd.DataFrame([(one["key"].iloc[0], i, n, slack) for i, n in counts.items()], columns=["key", "id", "n", "slack"])

    made = rows.select(F.col(key).cast("string").alias("key"), F.col("id").cast("long")).mapInPandas(summarise, SHAPE)
    return made.withColumn("part", F.spark_partition_id()).groupBy("key").applyInPandas(merge, SHAPE)


def lossy_counting(rows: DataFrame, key: str, eps: float) -> DataFrame:
    """(key, id, n, slack): ids whose count may exceed eps of the key's rows; the true count lies in [n, n + slack], slack at most eps of the rows plus one a partition."""
    width = max(1, round(1 / eps))

    def summarise(parts: Iterator[pd.DataFrame]):
        held, seen = {}, {}
        for part in parts:
            for k, i in zip(part["key"], part["id"]):
                table, at = held.setdefault(k, {}), seen.get(k, 0)
                seen[k] = at + 1
                n, slack = table.get(i, (0, at // width))
                table[i] = n + 1, slack
                if (at + 1) % width == 0:
                    turn = (at + 1) // width
                    held[k] = {j: v for j, v in table.items() if sum(v) > turn}
        rows_out = [(k, int(i), n, s, seen[k] // width) for k, t in held.items() for i, (n, s) in t.items()]
        rows_out += [(k, None, seen[k], 0, seen[k] // width) for k in seen]
        yield pd.DataFrame(rows_out, columns=["key", "id", "n", "slack", "most"]).astype({"id": "Int64"})

    # an id that a partition dropped may have had `most` rows there: totals of all partitions less those that still hold it
    made = rows.select(F.col(key).cast("string").alias("key"), F.col("id").cast("long")).mapInPandas(summarise, SHAPE + ", most long")
    per = made.where("id is null").groupBy("key").agg(F.sum("n").alias("all"), F.sum("most").alias("most_all"))
    held = made.where("id is not null").groupBy("key", "id").agg(F.sum("n").alias("n"), F.sum("slack").alias("s"), F.sum("most").alias("m"))
    return held.join(per, "key").select("key", "id", "n", (F.col("s") + F.col("most_all") - F.col("m")).alias("slack"), "all").where(F.col("n") + F.col("slack") >= eps * F.col("all")).select("key", "id", "n", "slack")


def merge_sketch(row: pd.Series, total: pd.Series, cand: pd.Series, votes: pd.Series) -> list:
    """[total, cand, votes] of cells of one place: the same merge as the engine's expressions, as an aggregate function for SQL users."""
    sums = {int(c): int(v) for c, v in votes.groupby(cand).sum().items()}
    return [int(total.sum()), *merged_place(int(row.iloc[0]), sums)]


def merged_place(row: int, votes: dict) -> tuple[int, int]:
    """(cand, votes) of a place from the votes of its candidates, ties by the salted hash of the engine's expressions."""
    order = sorted((-v, int(md5(f"{c}/{row}".encode()).hexdigest()[:7], 16), c) for c, v in votes.items())
    return order[0][2], -order[0][0] + (order[1][0] if len(order) > 1 else 0)


def packed_merge(cells: DataFrame, keys: list[str]) -> DataFrame:
    merge = F.pandas_udf(merge_sketch, "array<bigint>")
    made = cells.groupBy(*keys, "row", "col").agg(merge("row", "total", "cand", "votes").alias("m"))
    return made.select(*keys, "row", "col", F.col("m")[0].alias("total"), F.col("m")[1].alias("cand"), F.col("m")[2].alias("votes"))


def tree_reduced(cells: DataFrame, keys: list[str], depth: int = 2) -> dict:
    """The physical comparison of the tree merge: cells as Python dictionaries through RDD.treeReduce. Its result is on the driver, so it is for bounded sketches only."""

    def pack(rows):
        got: dict = {}
        for r in rows:
            at = (*(r[k] for k in keys), r["row"], r["col"])
            total, votes = got.get(at, (0, {}))
            got[at] = total + r["total"], {**votes, r["cand"]: votes.get(r["cand"], 0) + r["votes"]}
        yield got

    def join(a, b):
        for at, (total, votes) in b.items():
            t, v = a.get(at, (0, {}))
            a[at] = t + total, {c: v.get(c, 0) + votes.get(c, 0) for c in {*v, *votes}}
        return a

    return cells.rdd.mapPartitions(pack).treeReduce(join, depth)


def reduced_cells(cells: DataFrame, keys: list[str], depth: int = 2) -> DataFrame:
    """(keys, row, col, total, cand, votes): the cells that treeReduce leaves, as a DataFrame again. For bounded sketches only, like `tree_reduced`."""
    rows = [(*at, total, *merged_place(at[-2], votes)) for at, (total, votes) in tree_reduced(cells, keys, depth).items()]
    return cells.sparkSession.createDataFrame(rows, cells.select(*keys, "row", "col", "total", "cand", "votes").schema)


def sketch_columns(ident: int, depth: int, width: int) -> list[int]:
    """An id's column in each row of a sketch, as `sketch.column_of` gives it."""
    number = int(md5(str(ident).encode()).hexdigest()[:7], 16)
    return [(number * a + b) % PRIME % width for a, b in (hash_coefficients(SEED, r + 1)[r] for r in range(depth))]


def top_of(held: dict, k: int, depth: int, width: int) -> list[tuple[int, int, int]]:
    """(id, upper, votes) of the best candidates of one sketch, held as (row, col) to (total, cand, votes)."""
    best = []
    for ident in {cand for _, cand, _ in held.values()}:
        own = [held.get((r, c), (0, None, 0)) for r, c in enumerate(sketch_columns(ident, depth, width))]
        best.append((-max(v if c == ident else 0 for _, c, v in own), -min(t for t, _, _ in own), ident))
    return [(i, -u, -v) for v, u, i in sorted(best)[:k]]


def packed_top_k(cells: DataFrame, keys: list[str], k: int, depth: int, width: int) -> DataFrame:
    """(keys, rank, id) by an aggregate function over a sketch's cells, which are at most depth x width a group."""

    def sketch_top_k(row: pd.Series, col: pd.Series, total: pd.Series, cand: pd.Series, votes: pd.Series) -> list:
        held = {(int(r), int(c)): (int(t), int(i), int(v)) for r, c, t, i, v in zip(row, col, total, cand, votes)}
        return [i for i, _, _ in top_of(held, k, depth, width)]

    top = F.pandas_udf(sketch_top_k, "array<bigint>")
    made = cells.groupBy(*keys).agg(top("row", "col", "total", "cand", "votes").alias("t"))
    return made.select(*keys, F.posexplode("t").alias("place", "id")).select(*keys, (F.col("place") + 1).alias("rank"), "id")


def cogrouped_merge(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """(key, row, col, total, cand, votes): two sketches a key, at most depth x width cells each, merged side by side in one cogroup."""

    def merge(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out = []
        for at, part in pd.concat([a, b]).groupby([key, "row", "col"], sort=False):
            total, cand, votes = merge_sketch(part["row"], part["total"], part["cand"], part["votes"])
            out.append((*at, total, cand, votes))
        return pd.DataFrame(out, columns=[key, "row", "col", "total", "cand", "votes"])

    shape = left.select(key, "row", "col", "total", "cand", "votes").schema
    return left.groupBy(key).cogroup(right.groupBy(key)).applyInPandas(merge, shape)


def packed_estimates(counts: DataFrame) -> DataFrame:
    """(key, id, estimate) from the built-in count-min sketch: counts is (key, packed, id). The bytes are Spark's own public layout: version, total, depth, width, a multiplier a row, then the table."""

    @F.pandas_udf("long")
    def estimate(packed: pd.Series, ident: pd.Series) -> pd.Series:
        out, read = [], {}
        for data, i in zip(packed, ident):
            if data not in read:
                depth, width = (int.from_bytes(data[at : at + 4], "big") for at in (12, 16))
                numbers = np.frombuffer(data, ">i8", offset=20).astype("int64")
                read[data] = depth, width, numbers[:depth], numbers[depth:].reshape(depth, width)
            depth, width, by, table = read[data]
            least = None
            for r in range(depth):
                h = (int(by[r]) * int(i) + (1 << 63)) % (1 << 64) - (1 << 63)
                c = int(table[r][((h + (h >> 32)) & PRIME) % width])
                least = c if least is None else min(least, c)
            out.append(least)
        return pd.Series(out, dtype="int64")

    return counts.select("key", "id", estimate("packed", "id").alias("estimate"))
