"""Vote-count sketches: a grid of cells (total, cand, votes) that merges in any order, as long-form rows.

Cells are rows keyed by (…, row, col); only cells that hold something exist. A merge sums the totals, sums votes per
candidate, and the winner keeps its votes less the runner-up's. Ties go by a salted hash, so small ids are not favoured.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import hash_coefficients, token_number, universal

DEPTH, WIDTH, SEED = 2, 256, 11


def column_of(ident: Column, row: int, width: int, seed: int = SEED) -> Column:
    a, b = hash_coefficients(seed, row + 1)[row]
    return (universal(token_number(ident), a, b) % width).cast("int")


def salt(ident: Column, row: Column, table: Column | None = None) -> Column:
    parts = [ident.cast("string"), row.cast("string"), *([table.cast("string")] if table is not None else [])]
    return token_number(F.concat_ws("/", *parts))


def spread(rows: DataFrame, depth: int, width: int, seed: int = SEED) -> DataFrame:
    """A row per sketch row, with the id's column in it."""
    cells = F.array(*[F.struct(F.lit(r).alias("row"), column_of(F.col("id"), r, width, seed).alias("col")) for r in range(depth)])
    return rows.withColumn("_c", F.explode(cells)).select("*", "_c.row", "_c.col").drop("_c")


def _settle(votes: DataFrame, keys: list[str]) -> DataFrame:
    """votes: one row per (keys, row, col, cand) with t and v. Only places with several candidates need salts and a sort."""
    held = votes.groupBy(*keys, "row", "col").agg(F.sum("t").alias("total"), F.collect_list(F.struct("v", "cand")).alias("o"))
    order = F.transform("o", lambda x: F.struct((-x["v"]).alias("v"), salt(x["cand"], F.col("row")).alias("s"), x["cand"].alias("cand")))
    best = F.when(F.size("o") > 1, F.array_sort(order)).otherwise(F.transform("o", lambda x: F.struct((-x["v"]).alias("v"), F.lit(0).cast("long").alias("s"), x["cand"].alias("cand"))))
    got = held.select(*keys, "row", "col", "total", best.alias("o"))
    return got.select(*keys, "row", "col", "total", F.col("o")[0]["cand"].alias("cand"), (F.coalesce(F.get("o", F.lit(1))["v"], F.lit(0)) - F.col("o")[0]["v"]).alias("votes"))


def build_cells(buckets: DataFrame, keys: list[str], depth: int = DEPTH, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """Cells of buckets' ids (keys and id), order-free.

    An id stands once in a bucket, so a cell's winner has 1 vote if alone and 0 otherwise: the whole is one combinable
    aggregation (count and least salt), however large the bucket.
    """
    rows = spread(buckets, depth, width, seed)
    table = F.col("table_id") if "table_id" in keys else None
    per = rows.groupBy(*keys, "row", "col").agg(F.count("*").alias("total"), F.min(F.struct(salt(F.col("id"), F.col("row"), table).alias("s"), F.col("id").alias("c"))).alias("w"))
    return per.select(*keys, "row", "col", "total", F.col("w.c").alias("cand"), F.when(F.col("total") == 1, 1).otherwise(0).cast("long").alias("votes"))


def arrival_cells(buckets: DataFrame, keys: list[str], depth: int = DEPTH, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """Cells as one insert after another leaves them, ids arriving in their order.

    The ids of a bucket differ, so a cell's winner loses its vote to the next arrival and the one after takes the cell:
    after an odd number of arrivals the last has 1 vote, after an even number the last but one has none. A count and the
    two last arrivals of each cell tell all; both are cut before the shuffle, so a huge bucket costs two rows a task.
    """
    places = [*keys, "row", "col"]
    rows = spread(buckets, depth, width, seed).select(*places, "id")
    last = rows.withColumn("_r", F.row_number().over(Window.partitionBy(*places).orderBy(F.desc("id")))).where(F.col("_r") <= 2)
    two = last.groupBy(*places).agg(F.max(F.when(F.col("_r") == 1, F.col("id"))).alias("a"), F.max(F.when(F.col("_r") == 2, F.col("id"))).alias("b"))
    odd = F.col("total") % 2 == 1
    return rows.groupBy(*places).agg(F.count("*").alias("total")).join(two, places).select(*places, "total", F.when(odd, F.col("a")).otherwise(F.col("b")).alias("cand"), odd.cast("long").alias("votes"))


def merge_cells(cells: DataFrame, keys: list[str]) -> DataFrame:
    """One-level merge of all cells of equal (keys, row, col): one shuffle by place serves both sums. A place holds at most the cells of its tables and nodes."""
    by_place = cells.select(*keys, "row", "col", "cand", "total", "votes").repartition(*keys, "row", "col")
    votes = by_place.groupBy(*keys, "row", "col", "cand").agg(F.sum("total").alias("t"), F.sum("votes").alias("v"))
    return _settle(votes, keys)


CELL = "struct<node:int,total:bigint,cand:bigint,votes:bigint,s:bigint>"


def _pair(a: str, b: str, node: str) -> str:
    """The merge of two cells as an SQL expression of structs."""
    first = f"{a}.cand = {b}.cand or {a}.votes > {b}.votes or ({a}.votes = {b}.votes and ({a}.s < {b}.s or ({a}.s = {b}.s and {a}.cand < {b}.cand)))"
    return f"""named_struct('node', cast({node} as int), 'total', {a}.total + {b}.total, 'cand', if({first}, {a}.cand, {b}.cand),
        'votes', if({a}.cand = {b}.cand, {a}.votes + {b}.votes, abs({a}.votes - {b}.votes)), 's', if({first}, {a}.s, {b}.s))"""


def _lists(cells: DataFrame, keys: list[str], *extra: Column) -> DataFrame:
    """The cells of a place in one array in the order of nodes, of which there is at most one a node; extra columns may be keys."""
    cell = F.struct(F.col("node").cast("int").alias("node"), F.col("total").cast("long").alias("total"), F.col("cand").cast("long").alias("cand"), F.col("votes").cast("long").alias("votes"), salt(F.col("cand"), F.col("row")).alias("s"))
    return cells.select("*", *extra).groupBy(*keys, "row", "col").agg(F.array_sort(F.collect_list(cell)).alias("l"))


def fold_cells(cells: DataFrame, keys: list[str]) -> DataFrame:
    """Pairwise merges in the order of nodes, as a gatherer would make them one after another."""
    merged = F.expr(f"aggregate(slice(l, 2, size(l)), l[0], (a, b) -> {_pair('a', 'b', 'a.node')})")
    return _lists(cells, keys).withColumn("m", merged).select(*keys, "row", "col", "m.total", "m.cand", "m.votes")


def tree_cells(cells: DataFrame, keys: list[str], nodes: int, fan_in: int = 2) -> DataFrame:
    """Merges of neighbouring nodes in rounds, each dividing the nodes by fan_in: a shuffle a round, by place and next node.

    No task ever holds more than fan_in cells of a place, however many nodes there are.
    """
    merged = F.expr(f"aggregate(slice(l, 2, size(l)), l[0], (a, b) -> {_pair('a', 'b', 'a.node')})")
    while nodes > 1:
        met = _lists(cells, [*keys, "up"], F.floor(F.col("node") / fan_in).cast("int").alias("up"))
        cells = met.withColumn("m", merged).select(*keys, F.col("up").alias("node"), "row", "col", "m.total", "m.cand", "m.votes")
        nodes = -(-nodes // fan_in)
    return cells.drop("node")


def array_cells(cells: DataFrame, keys: list[str], rounds: int) -> DataFrame:
    """The rounds of the tree after one gather: one shuffle brings a place's cells together, the rounds run on its array of a cell a node."""
    up = "cast(x.node div 2 as int)"
    last = "try_element_at(acc, -1)"
    met = f"concat(slice(acc, 1, size(acc) - 1), array({_pair(last, 'x', up)}))"
    alone = f"concat(acc, array(named_struct('node', {up}, 'total', x.total, 'cand', x.cand, 'votes', x.votes, 's', x.s)))"
    out = _lists(cells, keys)
    for _ in range(rounds):
        # a place that one node alone holds has nothing to merge
        out = out.withColumn("l", F.expr(f"if(size(l) = 1, l, aggregate(l, cast(array() as array<{CELL}>), (acc, x) -> if(size(acc) > 0 and {last}.node = {up}, {met}, {alone})))"))
    return out.select(*keys, "row", "col", F.col("l")[0]["total"].alias("total"), F.col("l")[0]["cand"].alias("cand"), F.col("l")[0]["votes"].alias("votes"))


def estimate(cells: DataFrame, ids: DataFrame, keys: list[str], depth: int, width: int, seed: int = SEED) -> DataFrame:
    """(keys, id, upper, votes): bounds of ids' counts; ids is (keys, id)."""
    rows = spread(ids, depth, width, seed)
    hit = rows.join(cells, [*keys, "row", "col"], "left")
    return hit.groupBy(*keys, "id").agg(F.min(F.coalesce("total", F.lit(0))).alias("upper"), F.max(F.when(F.col("cand") == F.col("id"), F.col("votes")).otherwise(0)).alias("votes"))


def top_k(cells: DataFrame, keys: list[str], k: int, depth: int = DEPTH, width: int = WIDTH, seed: int = SEED, rank_by: str = "votes") -> DataFrame:
    """(keys, rank, id, upper, votes): candidates by lower bound, then upper, then id."""
    ids = cells.select(*keys, F.col("cand").alias("id")).distinct()
    first, second = ("votes", "upper") if rank_by == "votes" else ("upper", "votes")
    order = Window.partitionBy(*keys).orderBy(F.desc(first), F.desc(second), "id")
    ranked = estimate(cells, ids, keys, depth, width, seed).withColumn("rank", F.row_number().over(order))
    return ranked.where(F.col("rank") <= k).select(*keys, "rank", "id", "upper", "votes")


def heavy_hitters(cells: DataFrame, keys: list[str], phi: float, depth: int = DEPTH, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    total = cells.where("row = 0").groupBy(*keys).agg(F.sum("total").alias("all"))
    ids = cells.select(*keys, F.col("cand").alias("id")).distinct()
    return estimate(cells, ids, keys, depth, width, seed).join(total, keys).where(F.col("upper") >= phi * F.col("all")).select(*keys, "id", "upper", "votes")


def count_min(rows: DataFrame, keys: list[str], depth: int = DEPTH, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    return spread(rows, depth, width, seed).groupBy(*keys, "row", "col").agg(F.count("*").alias("total"))


def count_sketch(rows: DataFrame, keys: list[str], depth: int = 3, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    sign = 1 - 2 * (salt(F.col("id"), F.col("row")) % 2)
    return spread(rows, depth, width, seed).groupBy(*keys, "row", "col").agg(F.sum(sign).alias("total"))


def count_sketch_estimate(cells: DataFrame, ids: DataFrame, keys: list[str], depth: int = 3, width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """(keys, id, estimate): the median over rows of the signed totals that an id meets; ids is (keys, id)."""
    sign = 1 - 2 * (salt(F.col("id"), F.col("row")) % 2)
    hit = spread(ids, depth, width, seed).join(cells, [*keys, "row", "col"], "left")
    return hit.groupBy(*keys, "id").agg(F.median(sign * F.coalesce("total", F.lit(0))).alias("estimate"))


class VoteSketch:
    """Reference in plain Python: one sketch, inserts in arrival order. For tests."""

    def __init__(self, depth: int, width: int, columns):
        self.columns, self.cells = columns, {}
        self.depth, self.width = depth, width

    def insert(self, ident: int, w: int = 1) -> None:
        for r in range(self.depth):
            key = r, self.columns(ident, r)
            total, cand, votes = self.cells.get(key, (0, ident, 0))
            if cand == ident:
                votes += w
            elif votes >= w:
                votes -= w
            else:
                cand, votes = ident, w - votes
            self.cells[key] = total + w, cand, votes
