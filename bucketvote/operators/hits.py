"""Searches by common keys inside tasks: signatures, posting lists and the best of every query, without a row for a pair.

A join on keys makes a row for every bucket a query shares with a row of the data. Here each task turns its rows into
posting lists, batch by batch, and counts what the queries' keys reach; only the best of each query leave it. Where
queries are as many as rows, the lists are written to the shared folder and each task of queries reads them all. Several
ways of making keys are counted in one pass, and caps on buckets need no second index: each posting knows how many caps
drop it.

Keys are those of `functions.hashing`, made for a whole batch at once. Edge cases: rows without a token have no key; the
query's own id is left out; repeated ids are rows of their own.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass, field
from hashlib import md5
from math import sin

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import OFFSET, PRIME, coins, hash_coefficients
from ..sources.shared import opened, shared_folder, stored
from .pairs import Bag, block_at, names_in, similarity, write_blocks

#: Postings counted at once.
POSTINGS = 1 << 21
_EMPTY = np.iinfo(np.int64).max


@dataclass(frozen=True)
class Way:
    """One way of making keys; rows may also bring their signature (column `sig`)."""

    k: int
    tables: int
    options: dict = field(default_factory=dict)


def numbers(strings) -> np.ndarray:
    """`token_number` of strings."""
    return np.array([int(md5(s.encode()).hexdigest()[:7], 16) for s in strings], np.int64)


_SINES = [int(abs(sin(i + 1)) * 2**32) for i in range(61)]
_TURNS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))


def _first_words(words: list) -> np.ndarray:
    """The first 32 bits of the md5 of messages of one block; words are its 16 words, arrays or, where all agree, numbers."""
    first = a, b, c, d = [np.full(len(words[0]), x, np.uint32) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    # the last three steps leave the first word as it is
    for i in range(61):
        turn = i // 16
        if turn == 0:
            f, g = d ^ (b & (c ^ d)), i
        elif turn == 1:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif turn == 2:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * i % 16
        w = words[g]
        f += a
        f += np.uint32((_SINES[i] + w) & 0xFFFFFFFF) if isinstance(w, int) else w + np.uint32(_SINES[i])
        by = _TURNS[turn][i % 4]
        a, d, c, b = d, c, b, b + ((f << np.uint32(by)) | (f >> np.uint32(32 - by)))
    return b + first[0]


def id_numbers(ids: np.ndarray, *ends: str) -> np.ndarray:
    """[ends, ids]: `token_number` of each id as a string, with an end put to it."""
    ends = ends or ("",)
    out = np.empty((len(ends), len(ids)), np.int64)
    if not len(ids):
        return out
    if ids.min() < 0 or max(map(len, ends)) > 30 or not all(e.isascii() for e in ends):
        out[:] = [numbers(f"{i}{e}" for i in ids.tolist()) for e in ends]
        return out
    long = np.ones(len(ids), np.int8)
    for power in range(1, 19):
        long += ids >= 10**power
    for digits in np.unique(long).tolist():
        every = np.flatnonzero(long == digits)
        for at in (every[i : i + 8192] for i in range(0, len(every), 8192)):
            raw, left = np.zeros((len(at), 64), np.uint8), ids[at]
            for i in range(digits - 1, -1, -1):
                more = left // 10
                raw[:, i] = 48 + left - 10 * more
                left = more
            for e, end in enumerate(ends):
                size = digits + len(end)
                raw[:, digits:] = 0
                raw[:, digits : size + 1] = np.frombuffer(end.encode() + b"\x80", np.uint8)
                raw[:, 56:58] = 8 * size & 255, 8 * size >> 8
                block = np.ascontiguousarray(raw[:, : size // 4 * 4 + 4]).view("<u4").T
                words = [np.ascontiguousarray(x) for x in block] + [0] * (16 - len(block))
                words[14] = 8 * size
                out[e, at] = _first_words(words).byteswap() >> 4
    return out


def _borrowed(sig: np.ndarray, toss: np.ndarray) -> np.ndarray:
    """[bins, rows] with each empty bin filled from the next full one, to the right where toss holds."""
    out, bins = sig.copy(), range(len(sig))
    for way, right in ((bins, False), (bins[::-1], True)):
        held = np.full(sig.shape[1], _EMPTY)
        for j in way:  # what comes round the end
            held = np.where(sig[j] != _EMPTY, sig[j], held)
        for j in way:
            held = np.where(sig[j] != _EMPTY, sig[j], held)
            if toss[j] == right:
                out[j] = held
    return out


def filled_bins(row: np.ndarray, u: np.ndarray, n: int, bins: int, seed: int = 1, coin: str = "per_bin", offset: bool = False) -> np.ndarray:
    """[bins, rows]: the least hash of each bin, empty ones filled; u are the hashes of n rows that all hold one."""
    code = np.sort(((u * bins // PRIME * n + row) << 31) | u)
    place = code >> 31
    first = np.flatnonzero(np.diff(place, prepend=-1))
    sig = np.full(bins * n, _EMPTY)
    sig[place[first]] = code[first] & ((1 << 31) - 1)
    sig = sig.reshape(bins, n)
    if offset or coin == "closest_side":
        return _filled(sig.T, coin, offset, seed).T
    return _borrowed(sig, np.array(coins(bins, seed), bool) if coin == "per_bin" else np.ones(bins, bool))


_known: dict[str, int] = {}


def token_numbers(words: list[str]) -> np.ndarray:
    """`token_number` of words, of which a worker keeps some."""
    if len(_known) > 200_000:
        _known.clear()
    new = [w for w in words if w not in _known]
    _known.update(zip(new, numbers(new).tolist(), strict=True))
    return np.array([_known[w] for w in words], np.int64)


def _filled(sig: np.ndarray, coin: str, offset: bool, seed: int) -> np.ndarray:
    n, bins = sig.shape
    at, full = np.arange(bins), sig != _EMPTY
    left = np.maximum.accumulate(np.where(full, at, -1), axis=1)
    left = np.where(left < 0, left[:, -1:] - bins, left)
    right = np.minimum.accumulate(np.where(full, at, 2 * bins)[:, ::-1], axis=1)[:, ::-1]
    right = np.where(right >= 2 * bins, right[:, :1] + bins, right)
    go_left, go_right = at - left, right - at
    toss = np.array(coins(bins, seed), bool)
    pick = {"per_bin": toss, "always_right": np.ones(bins, bool), "closest_side": (go_right < go_left) | ((go_right == go_left) & toss)}[coin]
    value = np.take_along_axis(sig, np.where(pick, right, left) % bins, axis=1)
    return value + np.where(pick, go_right, go_left) * OFFSET if offset else value


def signature(bag: Bag, number: np.ndarray, bins: int, seed: int = 1, family: str = "one_permutation", coin: str = "per_bin", offset: bool = False) -> np.ndarray:
    """[rows, bins] of rows that all hold a token; number is that of each of the bag's words."""
    if family == "minhash":
        return np.stack([np.minimum.reduceat(((number * a + b) % PRIME)[bag.code], bag.start[:-1]) for a, b in hash_coefficients(seed, bins)], axis=1)
    a, b = hash_coefficients(seed, 1)[0]
    return filled_bins(bag.row, ((number * a + b) % PRIME)[bag.code], bag.n, bins, seed, coin, offset).T


def keys(sig: np.ndarray, k: int, tables: int, layout: str = "block") -> list[np.ndarray]:
    """A value a row, for each table, equal where all k values of the signature are."""
    out = []
    for t in range(tables):
        own = sig[:, t * k : (t + 1) * k] if layout == "block" else sig[:, t :: tables]
        out.append(own[:, 0].copy() if k == 1 else np.ascontiguousarray(own, ">i8").view(f"S{8 * k}").ravel())
    return out


def batch_keys(batch, ways: list[Way]) -> tuple[np.ndarray, list[list[np.ndarray]]]:
    """Ids in ascending order, and their keys by way and table."""
    import pyarrow as pa
    import pyarrow.compute as pc

    batch = batch.take(pa.array(np.argsort(batch.column("id").to_numpy(), kind="stable")))
    if "sig" in batch.schema.names:
        sig = batch.column("sig").flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(batch.num_rows, -1)
        return batch.column("id").to_numpy(), [keys(sig, w.k, w.tables) for w in ways]
    batch = batch.filter(pc.greater(pc.fill_null(pc.list_value_length(batch.column("tokens")), 0), 0))
    bag, made, out = Bag(batch.column("tokens")), {}, []
    number = numbers(bag.words.to_pylist())
    for w in ways:
        options = dict(w.options)
        layout, kind = options.pop("layout", "block"), (w.k * w.tables, *sorted(options.items()))
        if kind not in made:
            made[kind] = signature(bag, number, w.k * w.tables, **options) if bag.n else np.zeros((0, w.k * w.tables), np.int64)
        out.append(keys(made[kind], w.k, w.tables, layout))
    return batch.column("id").to_numpy(), out


@dataclass
class Hashed:
    """Ids in ascending order, and the hashes of their tokens, row after row; far smaller than their keys of many tables."""

    ids: np.ndarray
    u: np.ndarray
    start: np.ndarray

    @staticmethod
    def part(batch, seed: int = 1) -> tuple[np.ndarray, ...]:
        """What `of` takes, of a batch (id, tokens); rows without a token are left out."""
        import pyarrow.compute as pc

        a, b = hash_coefficients(seed, 1)[0]
        batch = batch.filter(pc.greater(pc.fill_null(pc.list_value_length(batch.column("tokens")), 0), 0))
        flat = batch.column("tokens").flatten().dictionary_encode()
        u = ((token_numbers(flat.dictionary.to_pylist()) * a + b) % PRIME).astype(np.uint32)
        return batch.column("id").to_numpy(), u[flat.indices.to_numpy()], pc.list_value_length(batch.column("tokens")).to_numpy(zero_copy_only=False).astype(np.int64)

    @staticmethod
    def of(parts: list) -> Hashed:
        ids, u, size = (np.concatenate(x) for x in zip(*parts, strict=True))
        parts.clear()
        order = np.argsort(ids, kind="stable")
        begin, size = (np.cumsum(size) - size)[order], size[order]
        start = np.concatenate([[0], np.cumsum(size)])
        out = np.empty_like(u)
        for a in range(0, len(ids), 1 << 16):
            cut = slice(start[a], start[min(a + (1 << 16), len(ids))])
            out[cut] = u[np.repeat((begin - start[:-1])[a : a + (1 << 16)], size[a : a + (1 << 16)]) + np.arange(cut.start, cut.stop)]
        return Hashed(ids[order], out, start)

    def cut(self, rows: np.ndarray) -> Hashed:
        """Some of the rows, in their order."""
        size = np.diff(self.start)[rows]
        start = np.concatenate([[0], np.cumsum(size)])
        return Hashed(self.ids[rows], self.u[np.repeat(self.start[rows] - start[:-1], size) + np.arange(start[-1])], start)

    def bins(self, bins: int, first: int, last: int, seed: int = 1, step: int = 1 << 15) -> np.ndarray:
        """[last - first, ids] of a signature of so many bins."""
        out = np.empty((last - first, len(self.ids)), np.uint32)
        for a in range(0, len(self.ids), step):
            cut = self.start[a : a + step + 1]
            row = np.repeat(np.arange(len(cut) - 1), np.diff(cut))
            out[:, a : a + step] = filled_bins(row, self.u[cut[0] : cut[-1]].astype(np.int64), len(cut) - 1, bins, seed)[first:last]
        return out


_ODD = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)


def mixed(sig: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """(a number a row, equal where the signature is, and seldom else; the signature as pairs of values) of [k, rows] below 2^31."""
    pairs = [sig[j].astype(np.uint64) << np.uint64(31) | (sig[j + 1] if j + 1 < len(sig) else np.uint64(0)) for j in range(0, len(sig), 2)]
    mix = pairs[0]
    for more in pairs[1:]:
        mix = (mix * np.uint64(_ODD[0]) ^ mix >> np.uint64(29)) + more * np.uint64(_ODD[1])
    return mix.view(np.int64), pairs


def codes(sig: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(a number a row, equal where all values of the signature are; for each number the first row that has it) of [k, rows] below 2^31."""
    import pandas as pd

    mix, pairs = mixed(sig)
    code, known = pd.factorize(mix)
    first = np.empty(len(known), np.int64)
    first[code[::-1]] = np.arange(len(code))[::-1]
    if len(pairs) > 1 and not all((x[first][code] == x).all() for x in pairs):  # different values of one mix
        code = pd.factorize(pairs[0].view(np.int64))[0]
        for x in pairs[1:]:
            own, many = pd.factorize(x.view(np.int64))
            code = pd.factorize(code * np.int64(len(many)) + own)[0]
        first = np.empty(code.max() + 1, np.int64)
        first[code[::-1]] = np.arange(len(code))[::-1]
    return code, first


def _columns(rows: DataFrame) -> DataFrame:
    return rows.select("id", "sig" if "sig" in rows.columns else "tokens")


def _salts(ids: np.ndarray, tables: int) -> np.ndarray:
    return id_numbers(ids, *[f"/{t}" for t in range(tables)])


def bounds(data: DataFrame, ways: list[Way], caps: tuple[int, ...], nodes: int) -> str:
    """A shared folder with (way, table, node, key, cap, salt, id): the last row that each cap keeps of a bucket that has so many; ways are of k = 1."""

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            ids, made = batch_keys(batch, ways)
            node = id_numbers(ids)[0] % nodes
            salts = _salts(ids, max(w.tables for w in ways))
            for i, w in enumerate(ways):
                for t in range(w.tables):
                    n = len(ids)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, i, np.int32)), pa.array(np.full(n, t, np.int32)), pa.array(node.astype(np.int32)), pa.array(made[i][t]), pa.array(salts[t]), pa.array(ids)], names=["way", "tab", "node", "key", "salt", "id"])

    rows = _columns(data).mapInArrow(task, "way int, tab int, node int, key long, salt long, id long")
    order = Window.partitionBy("way", "tab", "node", "key").orderBy("salt", "id")
    last = rows.withColumn("cap", F.row_number().over(order)).where(F.col("cap") <= max(caps)).where(F.col("cap").isin(*caps))
    path = shared_folder(data.sparkSession, "bounds")
    last.write.parquet(path)
    return path


class Caps:
    """The rows of `bounds`, read once a task: for each bucket and cap the last kept (salt, id)."""

    def __init__(self, folder: str, ways: int, caps: tuple[int, ...]):
        import pyarrow as pa
        import pyarrow.parquet as pq

        parts = []
        for name in names_in(folder):
            fs, inside = opened(f"{folder}/{name}")
            with fs.open_input_file(inside) as f:
                parts.append(pq.read_table(f))
        x = {c: t.to_numpy() for c, t in zip(parts[0].column_names, pa.concat_tables(parts).columns, strict=True)} if parts else None
        self.held = {}
        if x is None:
            return
        # way, table, node and cap are small numbers: one number of them
        kind = ((x["way"].astype(np.int64) * 4096 + x["tab"]) * 4096 + x["node"]) * len(caps) + np.searchsorted(caps, x["cap"])
        order = np.lexsort((x["key"], kind))
        kind, cut = kind[order], np.flatnonzero(np.diff(kind[order], prepend=-1))
        for a, b in zip(cut, [*cut[1:], len(kind)], strict=True):
            self.held[int(kind[a])] = tuple(x[c][order[a:b]] for c in ("key", "salt", "id"))

    def level(self, way: int, table: int, node: np.ndarray, nodes: int, key: np.ndarray, salt: np.ndarray, ids: np.ndarray, caps: int) -> np.ndarray:
        """How many caps do not keep each row: 0 if all do."""
        out = np.zeros(len(ids), np.uint8)
        for m in range(nodes):
            own = np.flatnonzero(node == m)
            for c in range(caps):
                got = self.held.get(((way * 4096 + table) * 4096 + m) * caps + c)
                if got is None:
                    continue
                at = np.searchsorted(got[0], key[own]).clip(max=len(got[0]) - 1)
                s, i = got[1][at], got[2][at]
                out[own] += (got[0][at] == key[own]) & ((salt[own] > s) | ((salt[own] == s) & (ids[own] > i)))
        return out


def posted(way: int, made: list[np.ndarray], ids: np.ndarray, levels: list[np.ndarray] | None) -> dict:
    """The posting lists of a batch: for each table its keys in order, where the rows of each begin, and the rows."""
    terms, starts, rows, kept = [], [], [], []
    for t, key in enumerate(made):
        order = np.argsort(key, kind="stable")
        own = key[order]
        first = np.flatnonzero(np.r_[True, own[1:] != own[:-1]]) if len(own) else np.zeros(0, np.int64)
        terms.append(own[first])
        starts.append(np.r_[first, len(own)].astype(np.int64) + t * len(ids))
        rows.append(order.astype(np.int32))
        if levels is not None:
            kept.append(levels[t][order])
    return {"way": way, "ids": ids, "terms": terms, "starts": starts, "rows": np.concatenate(rows), "level": np.concatenate(kept) if kept else None}


def write_index(data: DataFrame, ways: list[Way]) -> str:
    """A shared folder with the posting lists of every batch of rows by way."""

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            ids, made = batch_keys(batch, ways)
            for i in range(len(ways)):
                yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(posted(i, made[i], ids, None), 5)], pa.binary())], names=["block"])

    path = shared_folder(data.sparkSession, "postings")
    _columns(data).mapInArrow(task, "block binary").write.parquet(path)
    return path


def write_keys(queries: DataFrame, ways: list[Way]) -> str:
    """A shared folder with ids and keys of the queries, by batch."""

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(batch_keys(batch, ways), 5)], pa.binary())], names=["block"])

    path = shared_folder(queries.sparkSession, "query-keys")
    _columns(queries).mapInArrow(task, "block binary").write.parquet(path)
    return path


def joined(parts: list, ways: list[Way]) -> tuple[np.ndarray, list[list[np.ndarray]]]:
    """Batches of ids and keys as one."""
    ids = np.concatenate([p[0] for p in parts])
    return ids, [[np.concatenate([p[1][i][t] for p in parts]) for t in range(w.tables)] for i, w in enumerate(ways)]


def _blocks(folder: str):
    import pyarrow.parquet as pq

    for name in names_in(folder):
        fs, inside = opened(f"{folder}/{name}")
        with fs.open_input_file(inside) as f:
            for part in pq.ParquetFile(f).iter_batches(batch_size=1):
                yield pickle.loads(part.column(0)[0].as_py())


class Best:
    """The k first of each query by hits, then id, over blocks; and how many rows each query met, itself among them."""

    def __init__(self, queries: np.ndarray, k: int, tables: int):
        self.queries, self.k, self.tables = queries, k, tables
        self.floor, self.met = np.ones(len(queries), np.int64), np.zeros(len(queries), np.int64)
        self.q, self.id, self.hits = (np.zeros(0, np.int64) for _ in range(3))
        self.rank, self.more = np.zeros(0, np.int64), []

    def add(self, first: int, size: int, q: np.ndarray, row: np.ndarray, hits: np.ndarray, ids: np.ndarray) -> None:
        """Counts of queries first to first + size; q counts from 0; in the order of q, then row."""
        self.met[first : first + size] += np.bincount(q, minlength=size)
        keep = hits >= self.floor[first + q]
        q, row, hits = q[keep], row[keep], hits[keep]
        keep = ids[row] != self.queries[first + q]
        q, row, hits = q[keep], row[keep], hits[keep]
        # the k-th best count of each query here
        held = np.bincount(q * (self.tables + 1) + hits, minlength=size * (self.tables + 1)).reshape(size, -1)
        above = np.cumsum(held[:, ::-1], axis=1)[:, ::-1]
        least = np.where(above[:, 0] >= self.k, (above >= self.k).sum(axis=1) - 1, 0)
        more, tied = hits > least[q], np.flatnonzero(hits == least[q])
        # rows of a block are in the order of ids: of those at the bound the first k of each query do
        begin = np.searchsorted(q[tied], np.arange(size))
        more[tied] = np.arange(len(tied)) - begin[q[tied]] < self.k
        self.more.append((first + q[more], ids[row[more]], hits[more]))

    def settle(self) -> None:
        self.q, self.id, self.hits = (np.concatenate(x) for x in zip((self.q, self.id, self.hits), *self.more, strict=True))
        self.more = []
        order = np.lexsort((self.id, -self.hits, self.q))
        q = self.q[order]
        begin = np.searchsorted(q, np.arange(len(self.queries)))
        self.rank = np.arange(len(q)) - begin[q]
        keep = self.rank < self.k
        order, self.rank = order[keep], self.rank[keep]
        self.q, self.id, self.hits = self.q[order], self.id[order], self.hits[order]
        last = self.rank == self.k - 1
        self.floor[self.q[last]] = self.hits[last]


def _count(block: dict, asked: list[np.ndarray], to: list[tuple[int, Best]]) -> None:
    """Meets queries' keys with one block; to holds (number of caps below which those that drop a row must be, where to count)."""
    ids, nq = block["ids"], len(to[0][1].queries)
    n = len(ids)
    if not n or not nq:
        return
    start, many = np.zeros((nq, len(asked)), np.int64), np.zeros((nq, len(asked)), np.int64)
    for t, own in enumerate(asked):
        terms, starts = block["terms"][t], block["starts"][t]
        at = np.searchsorted(terms, own).clip(max=len(terms) - 1)
        start[:, t] = starts[at]
        many[:, t] = np.where(terms[at] == own, starts[at + 1] - starts[at], 0)
    total = np.cumsum(many.sum(axis=1))
    a = 0
    while a < nq:
        done = int(total[a - 1]) if a else 0
        b = max(a + 1, int(np.searchsorted(total, done + POSTINGS, "right")))
        m = many[a:b].ravel()
        ends = np.cumsum(m)
        source = np.arange(int(ends[-1])) + np.repeat(start[a:b].ravel() - (ends - m), m)
        place = block["rows"][source] + np.repeat(np.repeat(np.arange(b - a) * n, len(asked)), m)
        level = block["level"][source] if block["level"] is not None else None
        for allowed, best in to:
            here = place if level is None or allowed is None else place[level < allowed]
            if 4 * len(here) > (b - a) * n:
                dense = np.bincount(here, minlength=(b - a) * n)
                at = np.flatnonzero(dense)
                hits = dense[at]
            else:
                here = np.sort(here)
                edge = np.flatnonzero(np.diff(here, prepend=-1))
                at, hits = here[edge], np.diff(edge, append=len(here))
            q, row = np.divmod(at, n)
            best.add(a, b - a, q, row, hits, ids)
        a = b


TOPS = "way int, cap int, query_id long, rank int, id long, hits long"


def _rows(found: list[list[tuple]], ids: np.ndarray, caps: tuple[int, ...]):
    """What each way and cap has found, as batches; rank 0 holds the rows met."""
    import pyarrow as pa

    for i, own in enumerate(found):
        for cap, (_, best) in zip((*caps, 0), own, strict=True):
            met = np.flatnonzero(best.met)
            for q, rank, ident, hits in ((best.q, best.rank + 1, best.id, best.hits), (met, np.zeros(len(met), np.int64), ids[met], best.met[met])):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(q), i, np.int32)), pa.array(np.full(len(q), cap, np.int32)), pa.array(ids[q]), pa.array(rank.astype(np.int32)), pa.array(ident), pa.array(hits)], names=["way", "cap", "query_id", "rank", "id", "hits"])


def tops(data: DataFrame, queries: DataFrame, ways: list[Way], answers: int, caps: tuple[int, ...] = (), nodes: int = 1) -> DataFrame:
    """(way, cap, query_id, rank, id, hits): the first answers by common keys, then id, of each way, for each cap on buckets and for none (cap 0). Rank 0 holds in hits how many rows the query meets, itself among them.

    data and queries are (id, tokens), or (id, sig). Every task of the data meets all queries' keys and gives back the best of its rows; for queries as many as the data take `tops_of_many`.
    """
    caps = tuple(sorted(caps))
    folder, limits = write_keys(queries, ways), bounds(data, ways, caps, nodes) if caps else None

    def task(batches):
        parts = [p for p in _blocks(folder) if len(p[0])]
        if not parts:
            return
        ids, asked = joined(parts, ways)
        held = Caps(limits, len(ways), caps) if caps else None
        # a posting's level is how many caps drop it, and smaller caps drop first
        found = [[(c, Best(ids, answers, w.tables)) for c in (*range(1, len(caps) + 1), None)] for w in ways]
        for batch in batches:
            own, made = batch_keys(batch, ways)
            node, salts = (id_numbers(own)[0] % nodes, _salts(own, max(w.tables for w in ways))) if caps else (None, None)
            for i, w in enumerate(ways):
                levels = [held.level(i, t, node, nodes, made[i][t], salts[t], own, len(caps)) for t in range(w.tables)] if caps else None
                _count(posted(i, made[i], own, levels), asked[i], found[i])
                for _, best in found[i]:
                    best.settle()
        yield from _rows(found, ids, caps)

    rows = stored(_columns(data).mapInArrow(task, TOPS), "tops")
    order = Window.partitionBy("way", "cap", "query_id").orderBy(F.desc("hits"), "id")
    best = rows.where("rank > 0").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= answers)
    met = rows.where("rank = 0").groupBy("way", "cap", "query_id").agg(F.lit(0).alias("rank"), F.first("id").alias("id"), F.sum("hits").alias("hits"))
    return best.unionByName(met)


def tops_of_many(data: DataFrame, queries: DataFrame, ways: list[Way], answers: int) -> DataFrame:
    """`tops` without caps where queries are many: a query lies in one task, which reads the posting lists of all rows from the shared folder."""
    folder = write_index(data, ways)

    def task(batches):
        parts = [p for p in (batch_keys(b, ways) for b in batches if b.num_rows) if len(p[0])]
        if not parts:
            return
        ids, asked = joined(parts, ways)
        found = [[(None, Best(ids, answers, w.tables))] for w in ways]
        for block in _blocks(folder):
            own = found[block["way"]]
            _count(block, asked[block["way"]], own)
            own[0][1].settle()
        yield from _rows(found, ids, ())

    return _columns(queries).mapInArrow(task, TOPS)


def graded_pairs(found: DataFrame, data: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, id, similarity) of found pairs: exact cosines of their sets. Data is shuffled once by id; queries are read from files, so no pair carries tokens through a shuffle."""
    wanted = found.groupBy("id").agg(F.collect_set("query_id").alias("asking"))
    folder = write_blocks(queries.select("id", "tokens"))

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            bag = Bag(batch.column("tokens"))
            ids, lists = batch.column("id").to_numpy(), batch.column("asking")
            row = np.repeat(np.arange(len(ids)), np.diff(lists.offsets.to_numpy()))
            asking = lists.flatten().to_numpy()
            for name in names_in(folder):
                own = block_at(folder, name)
                order = np.argsort(own.ids, kind="stable")
                at = np.searchsorted(own.ids[order], asking).clip(max=max(0, len(order) - 1))
                here = np.flatnonzero(own.ids[order][at] == asking) if len(order) else np.zeros(0, np.int64)
                if not len(here):
                    continue
                q, d, codes = order[at[here]], row[here], own.tokens.codes(bag)
                dot = own.tokens.dot_pairs(bag, codes, q, d)
                yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in (asking[here], ids[d], dot, own.tokens.size[q], bag.size[d])], names=["query_id", "id", "dot", "nq", "nd"])

    both = data.select("id", "tokens").join(wanted, "id").select("id", "tokens", "asking")
    made = both.mapInArrow(task, "query_id long, id long, dot long, nq long, nd long")
    return made.select("query_id", "id", similarity().alias("similarity"))


def quality(data: DataFrame, queries: DataFrame, ways: list[Way], answers: int, caps: tuple[int, ...] = (), nodes: int = 1) -> DataFrame:
    """(way, cap, s_at_k, coverage, candidates): mean over queries of the mean cosine of their answers, the share of answers found, and the rows a query meets."""
    found = stored(tops(data, queries, ways, answers, caps, nodes), "answers")
    n = queries.count()
    held = found.where("rank > 0")
    scored = held.join(graded_pairs(held, data, queries), ["query_id", "id"])
    per = scored.groupBy("way", "cap", "query_id").agg(F.avg("similarity").alias("s"), F.count("*").alias("n"))
    load = found.where("rank = 0").groupBy("way", "cap").agg(F.round(F.sum("hits") / n, 3).alias("candidates"))
    return per.groupBy("way", "cap").agg(F.round(F.avg("s"), 6).alias("s_at_k"), F.round(F.sum("n") / (answers * n), 6).alias("coverage")).join(load, ["way", "cap"])
