"""Sketch cells made inside the task that holds a node's rows: the cells of `sketch.build_cells`, without a row for an id and table in any shuffle.

Rows are dealt by node, so a bucket of a node lies in one task; only a node of more than PART rows is built in parts,
whose cells are merged after a shuffle. Salts are made only where several ids meet in a cell. A bucket's key is its
values as bytes, eight for each.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, hash_coefficients
from . import hits, sketch
from .search import assign_nodes

#: Rows whose cells are made at once, unless a node has but few more; cells of a batch.
PART, BATCH = 2_500_000, 100_000


def columns(number: np.ndarray, depth: int, width: int) -> np.ndarray:
    """[depth, ids] columns of ids in the rows of a sketch; number is the `token_number` of each."""
    co = [hash_coefficients(sketch.SEED, r + 1)[r] for r in range(depth)]
    return np.stack([(number * a + b) % PRIME % width for a, b in co])


def of_table(bucket: np.ndarray, ids: np.ndarray, column: np.ndarray, width: int, row: int, table: int, salts: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """(bucket, col, total, cand, salt) of one row and table, in the order of bucket and col; salt is that of the winner where several met, else 0. Ids ascend within a bucket; salts are those of all ids, if they are known."""
    place, bits = bucket * width + column, len(ids).bit_length()
    # place and row in one number sort many times as fast as the places' order is found
    if len(place) and int(place.max()) < 1 << (62 - bits):
        code = np.sort(place << bits | np.arange(len(place)))
        order, held = code & ((1 << bits) - 1), code >> bits
    else:
        order = np.argsort(place, kind="stable")
        held = place[order]
    first = np.flatnonzero(np.diff(held, prepend=-1))
    total = np.diff(first, append=len(held))
    cand, least = ids[order[first]], np.zeros(len(first), np.int64)
    many = np.flatnonzero(total > 1)
    if len(many):
        here = order[np.repeat(total > 1, total)]
        salt = salts[here] if salts is not None else hits.id_numbers(ids[here], f"/{row}/{table}")[0]
        # the least salt, then the least id, as ids ascend
        best = np.minimum.reduceat(salt << bits | here, np.cumsum(total[many]) - total[many])
        cand[many], least[many] = ids[best & ((1 << bits) - 1)], best >> bits
    at, col = np.divmod(held[first], width)
    return at, col, total, cand, least


def _bytes(keys: np.ndarray):
    """[rows, k] values as an Arrow array of their bytes, eight for each."""
    import pyarrow as pa

    raw = np.ascontiguousarray(keys, ">i8")
    ends = np.arange(len(raw) + 1, dtype=np.int32) * (8 * raw.shape[1])
    return pa.BinaryArray.from_buffers(pa.binary(), len(raw), [None, pa.py_buffer(ends), pa.py_buffer(raw)])


#: Bytes of signatures held at once while the cells of a node are made.
SIGNED = 64 << 20


def node_index(rows: DataFrame, k: int, tables: int, nodes: int, depth: int = sketch.DEPTH, width: int = sketch.WIDTH, n: int | None = None) -> DataFrame:
    """(node, table_id, bucket_key, row, col, total, cand, votes) of rows (id, tokens), of which there are n: the sketch index of every node, made by the task that holds the node."""
    whole = 8 * (rows.count() if n is None else n) < 7 * nodes * PART

    def made(parts: list):
        import pyarrow as pa

        held = hits.Hashed.of(parts)
        ids = held.ids
        number = hits.id_numbers(ids)[0]
        node, column = number % nodes, columns(number, depth, width)
        names = ["node", "table_id", "bucket_key", "row", "col", "total", "cand", "votes"] + ["salt"] * (not whole)
        step = max(1, SIGNED // (4 * k * len(ids)))
        for t in range(tables):
            if t % step == 0:
                sig = held.bins(k * tables, k * t, k * min(tables, t + step))
            code, first = hits.codes(sig[t % step * k : (t % step + 1) * k])
            terms = sig[t % step * k : (t % step + 1) * k, first].T.astype(">i8")
            bucket = code * nodes + node
            for r in range(depth):
                at, col, total, cand, least = of_table(bucket, ids, column[r], width, r, t)
                term, own = np.divmod(at, nodes)
                for a in range(0, len(at), BATCH):
                    s = slice(a, a + BATCH)
                    m = len(at[s])
                    out = [pa.array(own[s].astype(np.int32)), pa.array(np.full(m, t, np.int32)), _bytes(terms[term[s]]), pa.array(np.full(m, r, np.int32)), pa.array(col[s].astype(np.int32)), pa.array(total[s]), pa.array(cand[s]), pa.array((total[s] == 1).astype(np.int64))]
                    yield pa.RecordBatch.from_arrays(out if whole else [*out, pa.array(least[s])], names=names)

    def task(batches):
        parts, held = [], 0
        for batch in batches:
            parts.append(hits.Hashed.part(batch))
            held += len(parts[-1][0])
            if held >= PART and not whole:
                yield from made(parts)
                held = 0
        if held:
            yield from made(parts)

    dealt = assign_nodes(rows.select("id", "tokens"), nodes).repartitionById(nodes, F.col("node"))
    cells = dealt.select("id", "tokens").mapInArrow(task, "node int, table_id int, bucket_key binary, row int, col int, total long, cand long, votes long" + ("" if whole else ", salt long"))
    if whole:
        return cells
    # nodes of several parts: the part that brought a cell alone knows no salt of its id yet
    salt = F.when(F.col("total") > 1, F.col("salt")).otherwise(sketch.salt(F.col("cand"), F.col("row"), F.col("table_id")))
    per = cells.groupBy("node", "table_id", "bucket_key", "row", "col").agg(F.sum("total").alias("total"), F.min(F.struct(salt.alias("s"), F.col("cand").alias("c"))).alias("w"))
    return per.select("node", "table_id", "bucket_key", "row", "col", "total", F.col("w.c").alias("cand"), F.when(F.col("total") == 1, 1).otherwise(0).cast("long").alias("votes"))
