"""Pairs of queries and rows inside tasks: common tokens and common keys are counted in blocks, and only what a query keeps leaves a task.

A join on tokens makes a row for nearly every pair, as words are few. Here the queries are written in blocks to the
shared folder; each task reads its own rows once and meets every block, and no pair is shuffled. Counts of a block are a
product of two matrices for the tokens that many queries hold and a sum over posting lists for all others: both are
exact whole numbers. What a task gives back are the counts and sizes of the kept pairs; similarities, rounding and the
final order are expressions on those, as after a join.

Edge cases: rows without a token meet nothing, and pairs without a common token are no pairs; the pair of an id with
itself is left out, unless asked for; repeated ids are rows of their own; no query or no row gives no rows.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.shared import opened, shared_folder, stored

#: Queries of a block, rows of a step, postings added at once, blocks that a worker keeps.
BLOCK, STEP, POSTINGS, HELD = 2048, 1024, 1 << 22, 6
#: Share of a block's queries beyond which a token is a column of the matrix.
COMMON = 0.02
#: Above all errors of a value in single precision, and of rounding to nine places.
SLACK = 1e-5
_MET = "query_id long, id long, dot long, nq long, nd long, hits long"


class Bag:
    """Lists of strings as (row, code, weight) with their dictionary; a repeated string of a list weighs its repeats."""

    def __init__(self, lists):
        lists = whole(lists)
        self.n = len(lists)
        flat = lists.flatten().dictionary_encode()
        counts = np.diff(lists.offsets.to_numpy()) if self.n else np.zeros(0, np.int64)
        self.words = flat.dictionary
        place = np.repeat(np.arange(self.n), counts) * max(1, len(self.words)) + flat.indices.to_numpy()
        place, self.weight = np.unique(place, return_counts=True)
        self.row, self.code = np.divmod(place, max(1, len(self.words)))
        self.plain = bool((self.weight == 1).all())
        #: Sum of squared weights: of sets their size.
        self.size = np.bincount(self.row, self.weight.astype(np.float64) ** 2, self.n).astype(np.int64)
        self.start = np.searchsorted(self.row, np.arange(self.n + 1))


class Postings:
    """A block's side of the product."""

    def __init__(self, bag: Bag):
        self.n, self.words, self.size, self.plain = bag.n, bag.words, bag.size, bag.plain
        order = np.argsort(bag.code, kind="stable")
        held = np.bincount(bag.code, minlength=len(bag.words))
        self.row, self.weight = bag.row[order], bag.weight[order]
        self.start = np.concatenate([[0], np.cumsum(held)])
        common = np.flatnonzero(held > max(8, COMMON * self.n))
        self.column = np.full(len(bag.words), -1)
        self.column[common] = np.arange(len(common))
        own = self.column[bag.code] >= 0
        # doubles where a sum could pass what single precision holds
        self.matrix = np.zeros((self.n, len(common)), np.float32 if self.plain else np.float64)
        self.matrix[bag.row[own], self.column[bag.code[own]]] = bag.weight[own]

    def codes(self, bag: Bag) -> np.ndarray:
        """This block's code of each of the bag's words, or -1."""
        import pyarrow.compute as pc

        return pc.fill_null(pc.index_in(bag.words, value_set=self.words), -1).to_numpy(zero_copy_only=False)

    def dot(self, bag: Bag, codes: np.ndarray, a: int, b: int) -> np.ndarray:
        """Products of the queries with the bag's rows a to b: [queries, rows]."""
        part, size = slice(bag.start[a], bag.start[b]), b - a
        t, r, w = codes[bag.code[part]], bag.row[part] - a, bag.weight[part]
        known = t >= 0
        t, r, w = t[known], r[known], w[known]
        column = self.column[t]
        dense = column >= 0
        matrix = self.matrix if bag.plain else self.matrix.astype(np.float64)
        right = np.zeros((matrix.shape[1], size), matrix.dtype)
        right[column[dense], r[dense]] = w[dense]
        out = matrix @ right
        t, r, w = t[~dense], r[~dense], w[~dense]
        first, many = self.start[t], self.start[t + 1] - self.start[t]
        ends, flat, at = np.cumsum(many), out.reshape(-1), 0
        while at < len(t):
            done = int(ends[at - 1]) if at else 0
            to = max(at + 1, int(np.searchsorted(ends, done + POSTINGS, "right")))
            m = many[at:to]
            source = np.arange(int(m.sum())) + np.repeat(first[at:to] - (ends[at:to] - m - done), m)
            place = self.row[source] * size + np.repeat(r[at:to], m)
            weights = None if bag.plain and self.plain else np.repeat(w[at:to], m) * self.weight[source]
            flat += np.bincount(place, weights, len(flat)).astype(flat.dtype)
            at = to
        return out

    def dot_pairs(self, bag: Bag, codes: np.ndarray, q: np.ndarray, d: np.ndarray) -> np.ndarray:
        """Products of given queries with given rows of the bag, pair by pair."""
        held = np.repeat(np.arange(len(self.words)), np.diff(self.start)) * self.n + self.row
        many, out, at = bag.start[d + 1] - bag.start[d], np.zeros(len(q), np.int64), 0
        ends = np.cumsum(many)
        while at < len(q) and len(held):
            done = int(ends[at - 1]) if at else 0
            to = max(at + 1, int(np.searchsorted(ends, done + POSTINGS, "right")))
            m = many[at:to]
            source = np.arange(int(m.sum())) + np.repeat(bag.start[d[at:to]] - (ends[at:to] - m - done), m)
            t, pair = codes[bag.code[source]], np.repeat(np.arange(to - at), m)
            place = t * self.n + q[at:to][pair]
            found = np.searchsorted(held, place).clip(max=len(held) - 1)
            same = (t >= 0) & (held[found] == place)
            out[at:to] = np.bincount(pair[same], bag.weight[source[same]] * self.weight[found[same]], to - at)
            at = to
        return out


class Block:
    def __init__(self, table):
        self.ids = table["id"].to_numpy()
        self.tokens = Postings(Bag(table["tokens"]))
        self.keys = Postings(Bag(table["keys"])) if "keys" in table.column_names else None
        self.sig = matrix_of(table["sig"]) if "sig" in table.column_names else None


def whole(lists):
    import pyarrow as pa

    return lists.combine_chunks() if isinstance(lists, pa.ChunkedArray) else lists


def matrix_of(lists) -> np.ndarray:
    """Lists of one length as rows."""
    flat = whole(lists).flatten().to_numpy(zero_copy_only=False)
    return flat.astype(np.int32).reshape(len(lists), -1) if len(lists) else np.zeros((0, 1), np.int32)


_blocks: dict[str, Block] = {}


def block_at(folder: str, name: str) -> Block:
    """A block read from the shared folder; a worker keeps the last few."""
    import pyarrow.parquet as pq

    path = f"{folder}/{name}"
    if path not in _blocks:
        while len(_blocks) >= HELD:
            _blocks.pop(next(iter(_blocks)))
        fs, inside = opened(path)
        with fs.open_input_file(inside) as f:
            _blocks[path] = Block(pq.read_table(f))
    return _blocks[path]


def names_in(folder: str) -> list[str]:
    from pyarrow import fs as pafs

    fs, inside = opened(folder)
    return sorted(f.base_name for f in fs.get_file_info(pafs.FileSelector(inside)) if f.base_name.endswith(".parquet"))


def write_blocks(queries: DataFrame, block: int | None = None) -> str:
    """A shared folder with the queries in files of about `block` rows."""
    block = block or BLOCK
    path = shared_folder(queries.sparkSession, "query-blocks")
    held = stored(queries, "queries")
    held.repartition(max(1, -(-held.count() // block))).write.parquet(path)
    return path


def _firsts(kinds: list[np.ndarray], ids: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k least ids of each kind."""
    order = np.lexsort((ids, *kinds[::-1]))
    new = np.zeros(len(order), bool)
    new[:1] = True
    for x in kinds:
        new[1:] |= np.diff(x[order]) != 0
    start = np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))
    return order[np.arange(len(order)) - start < k]


def _best(q: np.ndarray, value: np.ndarray, k: int, slack: float, floor: np.ndarray) -> np.ndarray:
    """Which rows may be among a query's k of highest value; raises floor to the k-th value of each query."""
    order = np.lexsort((-value, q))
    first = np.searchsorted(q[order], np.arange(len(floor)))
    full = np.searchsorted(q[order], np.arange(len(floor)), "right") - first >= k
    floor[full] = np.maximum(floor[full], value[order][first[full] + k - 1])
    return value >= floor[q] - slack


def met(data: DataFrame, queries: DataFrame, value: str = "cosine", top: int | None = None, least: float | None = None, min_hits: int = 0, exclude_self: bool = True, block: int | None = None) -> DataFrame:
    """(query_id, id, dot, nq, nd, hits) of the pairs that may be a query's `top` by `value`, or are of at least `least`; data and queries are (id, tokens[, keys]).

    `value` is "cosine" or "jaccard" of the tokens, or the number of common "hits" of the keys. Of pairs of equal value
    those of the smaller ids come first. Given pairs are a few more than asked for: the order and the bound are to be
    applied once more, by the exact expression. dot counts common tokens (of lists with repeats: the product of their
    counts), nq and nd are the sizes (the sums of squared counts), hits counts common keys.
    """
    keyed = "keys" in data.columns
    columns = ["id", "tokens", *(["keys"] if keyed else [])]
    folder = write_blocks(queries.select(*columns), block)

    def task(batches):
        import pyarrow as pa

        names, floors = names_in(folder), {}
        for batch in batches:
            if value == "hits":  # then positions break ties
                batch = batch.take(pa.array(np.argsort(batch.column("id").to_numpy(), kind="stable")))
            ids = batch.column("id").to_numpy()
            bag, keys = Bag(batch.column("tokens")), Bag(batch.column("keys")) if keyed else None
            for name in names:
                own = block_at(folder, name)
                if not len(own.ids):
                    continue
                codes, key_codes = own.tokens.codes(bag), own.keys.codes(keys) if keyed else None
                floor = floors.setdefault(name, np.zeros(len(own.ids)))
                local = floor * (len(ids) + 1) - len(ids) if value == "hits" else floor
                found = []
                for a in range(0, len(ids), STEP):
                    b = min(a + STEP, len(ids))
                    hits = own.keys.dot(keys, key_codes, a, b) if keyed else None
                    dot = own.tokens.dot(bag, codes, a, b)
                    nd, nq = bag.size[a:b].astype(dot.dtype), own.tokens.size.astype(dot.dtype)[:, None]
                    if value == "cosine":
                        worth = dot / np.sqrt(nd) / np.sqrt(nq)
                    elif value == "jaccard":
                        worth = dot / (nd + nq - dot)
                    else:
                        worth = np.where(hits > 0, hits.astype(np.float64) * (len(ids) + 1) - np.arange(a, b), -1.0)
                    gone = hits < max(1, min_hits) if value == "hits" or min_hits else None
                    if value != "hits":
                        gone = dot == 0 if gone is None else gone | (dot == 0)
                    if exclude_self:
                        gone |= own.ids[:, None] == ids[a:b]
                    worth[gone] = -1
                    if top is None:
                        at = np.nonzero(worth >= least - SLACK)
                    else:
                        if b - a > top:
                            local = np.maximum(local, np.partition(worth, -top, axis=1)[:, -top])
                        at = np.nonzero((worth > 0) & (worth >= (local - SLACK)[:, None]))
                    found.append((at[0], at[1] + a, dot[at].astype(np.int64), hits[at].astype(np.int64) if keyed else np.zeros(len(at[0]), np.int64), worth[at].astype(np.float64)))
                q, d, dot, hits, worth = (np.concatenate(x) for x in zip(*found, strict=True))
                nd = bag.size[d]
                if top is not None and len(q):
                    # rows of equal counts are of one value: of each such kind no more than `top` can be kept
                    few = _firsts([q, hits] if value == "hits" else [q, nd, dot], ids[d], top)
                    few = few[_best(q[few], worth[few], top, SLACK, local)]
                    q, d, dot, hits, nd = q[few], d[few], dot[few], hits[few], nd[few]
                    floors[name] = np.floor((local + len(ids)) / (len(ids) + 1)).clip(0) if value == "hits" else local
                yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in (own.ids[q], ids[d], dot, own.tokens.size[q], nd, hits)], names=["query_id", "id", "dot", "nq", "nd", "hits"])

    return data.select(*columns).mapInArrow(task, _MET)


def similarity(measure: str = "cosine") -> Column:
    """The exact similarity of a met pair; "weighted" is the cosine of counts."""
    dot, nq, nd = F.col("dot"), F.col("nq"), F.col("nd")
    if measure == "jaccard":
        return dot / (nq + nd - dot)
    if measure == "weighted":
        return dot / (F.sqrt(nd) * F.sqrt(nq))
    return dot / F.sqrt((nq * nd).cast("double"))


def ranked(data: DataFrame, queries: DataFrame, k: int, measure: str = "cosine", **options) -> DataFrame:
    """The k first pairs of each query, by similarity of nine places, then id: `met` with similarity and rank."""
    found = met(data, queries, "jaccard" if measure == "jaccard" else "cosine", top=k, **options).withColumn("similarity", similarity(measure))
    order = Window.partitionBy("query_id").orderBy(F.desc(F.round("similarity", 9)), "id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def most_similar(data: DataFrame, queries: DataFrame, k: int, measure: str = "cosine", **options) -> DataFrame:
    """(query_id, rank, id, similarity) of `ranked`."""
    return ranked(data, queries, k, measure, **options).select("query_id", "rank", "id", F.round("similarity", 6).alias("similarity"))


def most_hits(data: DataFrame, queries: DataFrame, k: int, **options) -> DataFrame:
    """(query_id, rank, id, hits, similarity): the k first of each query by common keys, then id, with their exact cosine; pairs without a common token have similarity 0."""
    found = met(data, queries, "hits", top=k, **options)
    order = Window.partitionBy("query_id").orderBy(F.desc("hits"), "id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", "hits", similarity().alias("similarity"))


def agreement(data: DataFrame, queries: DataFrame, near: float, far: float) -> DataFrame:
    """(p1, p2): mean share of agreeing signature values over pairs of Jaccard similarity `near` or more, and of `far` or less; data and queries are (id, tokens, sig)."""
    columns = ["id", "tokens", "sig"]
    folder = write_blocks(queries.select(*columns), None)

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            ids, bag, sig = batch.column("id").to_numpy(), Bag(batch.column("tokens")), matrix_of(batch.column("sig"))
            total = np.zeros(5, np.int64)
            for name in names_in(folder):
                own = block_at(folder, name)
                codes = own.tokens.codes(bag) if len(own.ids) else None
                for a in range(0, len(ids) if len(own.ids) else 0, STEP):
                    b = min(a + STEP, len(ids))
                    dot = own.tokens.dot(bag, codes, a, b).astype(np.float64)
                    met = (dot > 0) & (own.ids[:, None] != ids[a:b])
                    share = dot / (bag.size[a:b] + own.tokens.size[:, None] - dot)
                    same = np.zeros(dot.shape, np.uint16)
                    for i in range(sig.shape[1]):
                        same += own.sig[:, i, None] == sig[a:b, i]
                    one, two = met & (share >= near), met & (share <= far)
                    total += [same[one].sum(dtype=np.int64), one.sum(), same[two].sum(dtype=np.int64), two.sum(), 0]
            total[4] = sig.shape[1]
            yield pa.RecordBatch.from_arrays([pa.array([x]) for x in total.tolist()], names=["s1", "n1", "s2", "n2", "bins"])

    sums = data.select(*columns).mapInArrow(task, "s1 long, n1 long, s2 long, n2 long, bins long").agg(*[F.sum(c).alias(c) for c in ("s1", "n1", "s2", "n2")], F.max("bins").alias("bins"))
    return sums.select(*[F.round(F.col(f"s{i}") / F.col("bins") / F.when(F.col(f"n{i}") > 0, F.col(f"n{i}")), 6).alias(f"p{i}") for i in (1, 2)])
