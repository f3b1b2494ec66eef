"""Searches by sketch, merged over several numbers of nodes, inside tasks: what `search_index` gives with tree, linear and exact, without a row for a query's cells.

Only buckets that a query reaches are built. Each table's cells are made once by one task for every number of nodes and
lie in the shared folder; a task of queries reads them, merges the cells of a query on each node, then over nodes, and
gives back the answers. Ids are counted in the order of the ids reached, and in each row of a sketch by their salt, so
that a cell is one number that sorts by place, then as ties go. A task holds the reached buckets of one number of nodes.

Edge cases: rows without a token have no key; the query's own id is left out; a query that reaches nothing has no answer.
"""

from __future__ import annotations

import pickle

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.shared import opened, shared_folder, stored
from . import cells, hits
from .pairs import names_in
from .search import assign_nodes

ANSWERS = "strategy string, nodes int, query_id long, rank int, id long"


def _terms(folder: str, ways: list) -> list[np.ndarray]:
    """The queries' different keys by table."""
    parts = [p for p in hits._blocks(folder) if len(p[0])]
    return [np.unique(k) for k in hits.joined(parts, ways)[1][0]] if parts else []


def _reached(rows: DataFrame, asked: str, way) -> str:
    """A shared folder with (tab, bucket, id) of rows in a bucket that a query reaches, by table; a bucket is the place of its key among the queries' keys."""

    def task(batches):
        import pyarrow as pa

        terms = _terms(asked, [way])
        for batch in batches:
            ids, (keys,) = hits.batch_keys(batch, [way])
            for t, own in enumerate(terms):
                at = np.searchsorted(own, keys[t]).clip(max=len(own) - 1)
                here = np.flatnonzero(own[at] == keys[t])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(here), t, np.int32)), pa.array(at[here]), pa.array(ids[here])], names=["tab", "bucket", "id"])

    path = shared_folder(rows.sparkSession, "reached")
    rows.select("id", "tokens").mapInArrow(task, "tab int, bucket long, id long").write.partitionBy("tab").parquet(path)
    return path


def _table(folder: str) -> tuple[np.ndarray, ...]:
    import pyarrow.parquet as pq

    from pyarrow.fs import FileType

    parts = []
    fs, inside = opened(folder)
    if fs.get_file_info(inside).type == FileType.NotFound:  # no row reaches a bucket of this table
        return ()
    for name in names_in(folder):
        with fs.open_input_file(f"{inside}/{name}") as f:
            parts.append(pq.ParquetFile(f).read())
    return tuple(np.concatenate([p[c].to_numpy() for p in parts]) for c in parts[0].column_names) if parts else ()


class Ids:
    """The ids reached, in order; their columns, and in each row of a sketch their rank by salt, then id."""

    def __init__(self, folder: str, depth: int, width: int):
        got = _table(folder)
        self.ids = np.sort(got[0]) if got else np.zeros(0, np.int64)
        self.number = hits.id_numbers(self.ids)[0]
        self.column = cells.columns(self.number, depth, width)
        self.at, self.rank = [], []
        for r in range(depth):
            order = np.argsort(hits.id_numbers(self.ids, f"/{r}")[0], kind="stable")
            self.at.append(order)
            self.rank.append(np.empty(len(order), np.int64))
            self.rank[r][order] = np.arange(len(order))


_ids: dict = {}


def ids_of(folder: str, depth: int, width: int) -> Ids:
    """A worker keeps those of the last search."""
    if folder not in _ids:
        _ids.clear()
        _ids[folder] = Ids(folder, depth, width)
    return _ids[folder]


def _starts(bucket: np.ndarray, buckets: int) -> np.ndarray:
    return np.searchsorted(bucket, np.arange(buckets + 1))


def _write_tables(spark, reached: str, known: str, asked: str, way, nodes: tuple[int, ...], depth: int, width: int) -> str:
    """A shared folder with a file for each table and number of nodes: by row where each bucket's cells begin, the cells as numbers and their totals; and one with the ids of each bucket."""
    path = shared_folder(spark, "cells")

    def task(batches):
        import pyarrow as pa

        fs, inside = opened(path)
        fs.create_dir(inside, recursive=True)

        def put(name, what):
            with fs.open_output_stream(f"{inside}/{name}") as out:
                out.write(pickle.dumps(what, 5))

        for batch in batches:
            for t in batch.column("id").to_pylist():
                held, got = ids_of(known, depth, width), _table(f"{reached}/tab={t}")
                bucket, ids = got if got else (np.zeros(0, np.int64),) * 2
                buckets, row = len(_terms(asked, [way])[t]), np.searchsorted(held.ids, ids)
                order = np.lexsort((row, bucket))
                bucket, ids, row = bucket[order], ids[order], row[order]
                put(f"{t}-0", (_starts(bucket, buckets), row.astype(np.int32)))
                salts = hits.id_numbers(ids, *[f"/{r}/{t}" for r in range(depth)])
                for m in nodes:
                    node, made = held.number[row] % m, []
                    for r in range(depth):
                        at, col, total, cand, _ = cells.of_table(bucket * m + node, ids, held.column[r][row], width, r, t, salts[r])
                        own, on = np.divmod(at, m)
                        place = (on * depth + r) * width + col
                        made.append((_starts(own, buckets), (place << 33) | (held.rank[r][np.searchsorted(held.ids, cand)] << 1) | (total == 1), total.astype(np.int32)))
                    put(f"{t}-{m}", made)
                yield pa.RecordBatch.from_arrays([pa.array([t], pa.int64())], names=["id"])

    spark.range(0, way.tables, 1, way.tables).mapInArrow(task, "id long").count()
    return path


def _read(folder: str, name: str):
    fs, inside = opened(f"{folder}/{name}")
    with fs.open_input_file(inside) as f:
        return pickle.loads(f.read())


NONE = np.int64(1) << 40


def _local(codes: np.ndarray, totals: np.ndarray, places: int, bits: int = 32) -> tuple[np.ndarray, ...]:
    """(rank of the winner or NONE, votes, total) by place, of cells; ranks have so many bits."""
    total = np.bincount(codes >> 33, totals, places).astype(np.int64)
    codes = np.sort(codes)
    whose = codes >> 1
    first = np.flatnonzero(np.diff(whose, prepend=-1))
    votes = np.add.reduceat(codes & 1, first)
    place, rank = whose[first] >> 32, whose[first] & 0xFFFFFFFF
    # most votes first, then the least rank: fewer than 2^14 votes
    best = np.sort((place << (14 + bits)) | ((0x3FFF - votes) << bits) | rank)
    place = best >> (14 + bits)
    lead = np.flatnonzero(np.diff(place, prepend=-1))
    held = 0x3FFF - ((best >> bits) & 0x3FFF)
    two = np.minimum(lead + 1, len(best) - 1)
    second = np.where((lead + 1 < len(best)) & (place[two] == place[lead]), held[two], 0)
    winner, left = np.full(places, NONE), np.zeros(places, np.int64)
    winner[place[lead]], left[place[lead]] = best[lead] & ((1 << bits) - 1), held[lead] - second
    return winner, left, total


def _merged(a, b):
    """Cells of two nodes, that of the lower one first."""
    (wa, va, ta), (wb, vb, tb) = a, b
    same = wa == wb
    first = same | (va > vb) | ((va == vb) & (wa < wb))
    return np.where(first, wa, wb), np.where(same, va + vb, np.abs(va - vb)), ta + tb


def tree_of(local: tuple, nodes: int) -> tuple:
    """Neighbours of [nodes, …] cells in rounds."""
    x = tuple(v.reshape(nodes, -1) for v in local)
    while len(x[0]) > 1:
        even = len(x[0]) // 2 * 2
        up = _merged(tuple(v[0:even:2] for v in x), tuple(v[1:even:2] for v in x))
        x = tuple(np.concatenate([u, v[even:]]) for u, v in zip(up, x, strict=True))
    return tuple(v[0] for v in x)


def linear_of(local: tuple, nodes: int) -> tuple:
    """One node's cells after another's."""
    x = [tuple(v.reshape(nodes, -1)[i] for v in local) for i in range(nodes)]
    out = x[0]
    for more in x[1:]:
        out = _merged(out, more)
    return out


def _tops(merged: tuple, held: Ids, depth: int, width: int, answers: int, own: int) -> np.ndarray:
    """Ids of the best candidates of merged cells by votes, upper bound, then id; the query's own is left out."""
    winner, votes, total = (v.reshape(depth, width) for v in merged)
    ids = np.unique(np.concatenate([held.at[r][winner[r][winner[r] < NONE]] for r in range(depth)]))
    upper, least = None, np.zeros(len(ids), np.int64)
    for r in range(depth):
        col = held.column[r][ids]
        upper = total[r][col] if upper is None else np.minimum(upper, total[r][col])
        least = np.maximum(least, np.where(winner[r][col] == held.rank[r][ids], votes[r][col], 0))
    found = held.ids[ids[np.lexsort((ids, -upper, -least))[: answers + 1]]]
    return found[found != own][:answers]


def _exact(rows: np.ndarray, held: Ids, answers: int, own: int) -> np.ndarray:
    """Ids of the most hits, then the least id."""
    rows = np.sort(rows)
    first = np.flatnonzero(np.diff(rows, prepend=-1))
    rows, met = rows[first].astype(np.int64), np.diff(first, append=len(rows))
    code = ((0x3FFF - met) << 40) | rows
    if len(code) > answers + 1:
        code = np.partition(code, answers)[: answers + 1]
    found = held.ids[np.sort(code) & ((1 << 40) - 1)]
    return found[found != own][:answers]


def searches(rows: DataFrame, queries: DataFrame, k: int, tables: int, nodes: tuple[int, ...], answers: int, depth: int, width: int) -> DataFrame:
    """(strategy, nodes, query_id, rank, id): the answers of tree and linear on each number of nodes, and of exact counts, which are the same on any number (nodes 0)."""
    if tables >= 1 << 13 or max(nodes) * depth * width >= 1 << 17:
        raise ValueError("too many tables or cells for one number a cell")
    spark, way = rows.sparkSession, hits.Way(k, tables)
    asked = hits.write_keys(queries, [way])
    reached = _reached(rows, asked, way)
    known = shared_folder(spark, "ids")
    spark.read.schema("tab int, bucket long, id long").parquet(reached).select("id").distinct().write.parquet(known)
    folder = _write_tables(spark, reached, known, asked, way, nodes, depth, width)

    def task(batches):
        import pyarrow as pa

        parts = [p for p in (hits.batch_keys(b, [way]) for b in batches if b.num_rows) if len(p[0])]
        if not parts:
            return
        ids, (keys,) = hits.joined(parts, [way])
        held, terms = ids_of(known, depth, width), _terms(asked, [way])
        # every key here is one of the queries'
        bucket = [np.searchsorted(own, key) for own, key in zip(terms, keys, strict=True)]

        def rows_of(strategy, m, found):
            many = [len(x) for x in found]
            rank = np.concatenate([np.arange(1, n + 1, dtype=np.int32) for n in many])
            return pa.RecordBatch.from_arrays([pa.array([strategy] * len(rank), pa.string()), pa.array(np.full(len(rank), m, np.int32)), pa.array(np.repeat(ids, many)), pa.array(rank), pa.array(np.concatenate(found))], names=["strategy", "nodes", "query_id", "rank", "id"])

        held_rows = [_read(folder, f"{t}-0") for t in range(tables)]
        yield rows_of("exact", 0, [_exact(np.concatenate([x[start[b[i]] : start[b[i] + 1]] for b, (start, x) in zip(bucket, held_rows, strict=True)]), held, answers, own) for i, own in enumerate(ids.tolist())])
        del held_rows
        for m in nodes:
            made = [(b, *x) for t, b in enumerate(bucket) for x in _read(folder, f"{t}-{m}")]
            found = {"tree": [], "linear": []}
            for i, own in enumerate(ids.tolist()):
                cut = [(x, total, start[b[i]], start[b[i] + 1]) for b, start, x, total in made]
                local = _local(np.concatenate([x[a:z] for x, _, a, z in cut]), np.concatenate([total[a:z] for _, total, a, z in cut]), m * depth * width)
                for name, merge in (("tree", tree_of), ("linear", linear_of)):
                    found[name].append(_tops(merge(local, m), held, depth, width, answers, own))
            for name, x in found.items():
                yield rows_of(name, m, x)

    many = 4 * spark.sparkContext.defaultParallelism
    return stored(queries.select("id", "tokens").repartition(many).mapInArrow(task, ANSWERS), "answers")


def known_ids(rows: DataFrame) -> str:
    """A shared folder with the different ids of rows."""
    path = shared_folder(rows.sparkSession, "ids")
    rows.select("id").distinct().write.parquet(path)
    return path


def write_index(rows: DataFrame, known: str, k: int, tables: int, nodes: int, depth: int, width: int) -> str:
    """A shared folder with the whole index of every node, a file for each node and table: the buckets' keys in the order
    of their mixes, and by bucket the ids and the cells of each row of the sketch. Ids are their places among the known ones."""
    path = shared_folder(rows.sparkSession, "index")

    def task(batches):
        import pyarrow as pa

        # a task may hold several nodes
        parts = [p for p in (hits.Hashed.part(b) for b in batches) if len(p[0])]
        if not parts:
            return
        all_ids, every = ids_of(known, depth, width), hits.Hashed.of(parts)
        fs, inside = opened(path)
        fs.create_dir(inside, recursive=True)
        on = hits.id_numbers(every.ids)[0] % nodes
        for node in np.unique(on).tolist():
            held = every.cut(np.flatnonzero(on == node))
            row, bits = np.searchsorted(all_ids.ids, held.ids), len(held.ids).bit_length()
            step = max(1, cells.SIGNED // (4 * k * len(row)))
            for t in range(tables):
                if t % step == 0:
                    sig = held.bins(k * tables, k * t, k * min(tables, t + step))
                own = sig[t % step * k : (t % step + 1) * k]
                code, first = hits.codes(own)
                mix = hits.mixed(own[:, first])[0]
                by = np.argsort(mix)
                place = np.empty(len(by), np.int64)
                place[by] = np.arange(len(by))
                code = place[code]
                order = np.sort(code << bits | np.arange(len(code)))
                made = [(_starts(order >> bits, len(by)).astype(np.int32), row[order & ((1 << bits) - 1)].astype(np.uint32))]
                for r in range(depth):
                    at, col, total, cand, _ = cells.of_table(code, held.ids, all_ids.column[r][row], width, r, t)
                    many = np.flatnonzero(total > 1)
                    made.append((_starts(at, len(by)).astype(np.int32), col.astype(np.uint16 if width <= 1 << 16 else np.uint32), np.searchsorted(all_ids.ids, cand).astype(np.uint32), many.astype(np.int32), total[many].astype(np.int32)))
                with fs.open_output_stream(f"{inside}/{t}-{node}") as out:
                    out.write(pickle.dumps((mix[by], own[:, first[by]], made), 5))
            yield pa.RecordBatch.from_arrays([pa.array([node], pa.int32())], names=["node"])

    dealt = assign_nodes(rows.select("id", "tokens"), nodes).repartitionById(nodes, F.col("node"))
    dealt.select("id", "tokens").mapInArrow(task, "node int").count()
    return path


def _bucket_of(mix: np.ndarray, terms: np.ndarray, asked: np.ndarray) -> np.ndarray:
    """The place of each asked signature [k, queries] among a file's, or -1."""
    want = hits.mixed(asked)[0]
    at, last = np.searchsorted(mix, want), len(mix) - 1
    out = np.full(len(want), -1)
    while True:
        here = at.clip(max=last)
        same = (at <= last) & (mix[here] == want) & (out < 0)
        if not same.any():
            return out
        out[same & (terms[:, here] == asked).all(axis=0)] = here[same & (terms[:, here] == asked).all(axis=0)]
        at = at + 1  # another key of the same mix


def _gathered(start: np.ndarray, bucket: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places in a file's lists of what each query reaches, how many of each query)."""
    begin = np.where(bucket < 0, 0, start[bucket])
    many = np.where(bucket < 0, 0, start[np.maximum(bucket, 0) + 1] - begin)
    return np.repeat(begin - (np.cumsum(many) - many), many) + np.arange(many.sum()), many


#: Queries whose cells a task gathers at once; places that it merges at once.
ASKED, PLACES = 512, 1 << 18


def search_stored(queries: DataFrame, index: str, known: str, k: int, tables: int, nodes: int, answers: int, depth: int, width: int, strategy: str) -> DataFrame:
    """(query_id, rank, id): answers of tree, linear or exact from a stored index (`write_index`); nothing runs before they are asked for."""
    if strategy not in ("tree", "linear", "exact"):
        raise ValueError(strategy)
    if tables >= 1 << 13 or nodes * depth * width >= 1 << 20:
        raise ValueError("too many tables or cells for one number a cell")
    block = max(1, PLACES // (nodes * depth * width))
    merge = {"tree": tree_of, "linear": linear_of}.get(strategy)

    def answered(asked: hits.Hashed, held: Ids) -> list[np.ndarray]:
        from pyarrow.fs import FileSelector

        n = len(asked.ids)
        sig, cut = asked.bins(k * tables, 0, k * tables), np.r_[0:n:block, n]
        pieces = []  # (values, totals, where each block of queries begins)
        fs, inside = opened(index)
        there = {x.base_name for x in fs.get_file_info(FileSelector(inside))}
        for t in range(tables):
            own = sig[k * t : k * (t + 1)]
            for node in range(nodes):
                if f"{t}-{node}" not in there:  # a node without a row
                    continue
                mix, terms, made = _read(index, f"{t}-{node}")
                bucket = _bucket_of(mix, terms, own)
                for r, (start, *what) in enumerate(made[:1] if merge is None else made[1:]):
                    at, many = _gathered(start, bucket)
                    begin, q = np.r_[0, np.cumsum(many)][cut], np.repeat(np.arange(n) % block, many)
                    if merge is None:
                        pieces.append((q << 40 | what[0][at], None, begin))
                        continue
                    col, cand, several, more = what
                    total = np.ones(len(col), np.int32)
                    total[several] = more
                    total = total[at]
                    place = ((node * block + q) * depth + r) * width + col[at]
                    pieces.append((place << 33 | held.rank[r][cand[at]] << 1 | (total == 1), total, begin))
        out = []
        for b in range(len(cut) - 1):
            codes = np.concatenate([x[begin[b] : begin[b + 1]] for x, _, begin in pieces])
            ids = asked.ids[cut[b] : cut[b + 1]].tolist()
            if merge is None:
                codes.sort()
                edge = np.searchsorted(codes >> 40, np.arange(len(ids) + 1))
                out += [_exact(codes[edge[i] : edge[i + 1]] & ((1 << 40) - 1), held, answers, own) for i, own in enumerate(ids)]
                continue
            local = _local(codes, np.concatenate([x[begin[b] : begin[b + 1]] for _, x, begin in pieces]), nodes * block * depth * width, max(1, len(held.ids).bit_length()))
            merged = merge(local, nodes)
            out += [_tops(tuple(v[i * depth * width : (i + 1) * depth * width] for v in merged), held, depth, width, answers, own) for i, own in enumerate(ids)]
        return out

    def task(batches):
        import pyarrow as pa

        parts = [p for p in (hits.Hashed.part(b) for b in batches) if len(p[0])]
        if not parts:
            return
        every, held = hits.Hashed.of(parts), ids_of(known, depth, width)
        for a in range(0, len(every.ids), ASKED):
            asked = every.cut(np.arange(a, min(a + ASKED, len(every.ids))))
            found = answered(asked, held)
            many = [len(x) for x in found]
            rank = np.concatenate([np.arange(1, x + 1, dtype=np.int32) for x in many])
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(asked.ids, many)), pa.array(rank), pa.array(np.concatenate(found))], names=["query_id", "rank", "id"])

    many = queries.sparkSession.sparkContext.defaultParallelism
    return queries.select("id", "tokens").repartition(many).mapInArrow(task, "query_id long, rank int, id long")
