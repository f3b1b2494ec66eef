"""Packs documents into sequences of bounded token count: dominance reduction, then best fit on what remains.

Only lengths matter, and there are at most `capacity` of them, so the instance is a histogram of that size. The
reduction takes lengths from the largest and fixes bins that no alternative can beat; best fit, largest first, places
the rest, whole groups of equal bins at a time. Both work on counts: cost and memory do not grow with the documents.
Documents then find their places by their rank among pieces of equal length.

Edge cases: a null or empty text is one piece of the end id; a null doc_id is kept; repeated rows are packed once per
row; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from bisect import bisect_left, insort

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import id_in, id_out, lean, written
from .tokens import END_ID, encoder

CAPACITY = 4096
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, tie long"


def token_pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY) -> DataFrame:
    """A row per piece of each document's ids with the end id; only documents over the capacity are cut."""

    def task(batches):
        import pandas as pd

        enc, end = encoder(tokenizer), struct.pack("<I", END_ID)
        for batch in batches:
            out = []
            for doc_id, text, tie in zip(batch["doc_id"], batch["text"], batch["tie"], strict=True):
                ids = (enc.encode(text) if isinstance(text, str) else b"") + end
                for piece, a in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[a : a + 4 * capacity]
                    out.append((doc_id, piece, a // 4, len(part) // 4, zlib.crc32(part), tie))
            yield pd.DataFrame(out, columns=["doc_id", "piece", "start", "length", "ids_crc32", "tie"])

    return id_out(docs.select(id_in("doc_id"), "text", F.xxhash64("doc_id", "text").alias("tie")).mapInPandas(lean(task), PIECES), "doc_id")


def reduce_dominated(counts: dict[int, int], capacity: int) -> tuple[list[tuple[tuple[int, ...], int]], dict[int, int]]:
    """Bins (lengths, how many) that can be fixed for good, and the counts that remain.

    With the largest open length a, and k the longest that fits beside it, {a, k} is as good as any bin with a when it
    is full, when no third piece fits, or when no two pieces that fit together exceed k.
    """
    left = dict(counts)
    fixed: list[tuple[tuple[int, ...], int]] = []
    sizes = sorted(left)
    for a in sorted(left, reverse=True):
        while left.get(a):
            room = capacity - a
            n = left[a]
            i = bisect_left(sizes, room + 1) - 1
            while i >= 0 and (left[sizes[i]] - (sizes[i] == a)) <= 0:
                i -= 1
            if i < 0:
                fixed.append(((a,), n))
                left[a] = 0
                break
            k = sizes[i]
            if k != room and not _beats_pairs(left, sizes[: i + 1], a, k, room):
                break
            m = n // 2 if k == a else min(n, left[k])
            fixed.append(((a, k), m))
            left[a] -= m
            left[k] -= m
    return fixed, {s: n for s, n in left.items() if n}


def _beats_pairs(left: dict[int, int], sizes: list[int], a: int, k: int, room: int) -> bool:
    """Whether no two or more pieces that fit in the room together are longer than k."""
    free = [(s, left[s] - (s == a)) for s in sizes if left[s] - (s == a) > 0]
    smallest = [s for s, n in free[:3] for _ in range(min(n, 3))][:3]
    if len(smallest) < 2 or smallest[0] + smallest[1] > room:
        return True
    if len(smallest) == 3 and sum(smallest) <= room:
        return False
    i, j = 0, len(free) - 1
    while i <= j:
        both = free[i][0] + free[j][0]
        if both > room or (i == j and free[i][1] < 2):
            j -= 1
        elif both > k:
            return False
        else:
            i += 1
    return True


def best_fit(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit, longest first, on counts: bins of equal content move together and split only where pieces run out."""
    rooms: list[int] = []
    groups: dict[int, list[list]] = {}

    def put(room: int, content: tuple[int, ...], n: int) -> None:
        if room not in groups:
            groups[room] = []
            insort(rooms, room)
        groups[room].append([content, n])

    for size in sorted(counts, reverse=True):
        n = counts[size]
        while n:
            i = bisect_left(rooms, size)
            if i == len(rooms):
                each = min(n, capacity // size)
                if each:
                    put(capacity - each * size, (size,) * each, n // each)
                    n -= n // each * each
                continue
            room = rooms[i]
            content, have = groups[room][-1]
            each = min(room // size, n)
            m = min(have, n // each)
            if m == have:
                groups[room].pop()
                if not groups[room]:
                    del groups[room]
                    rooms.pop(i)
            else:
                groups[room][-1][1] = have - m
            put(room - each * size, (*content, *(size,) * each), m)
            n -= m * each
    return [(tuple(content), n) for room in groups for content, n in groups[room]]


def solve(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    fixed, rest = reduce_dominated(counts, capacity)
    return fixed + best_fit(rest, capacity)


def slots(bins: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, ranks, copies a bin, first sequence, offset in it) for runs of equal pieces."""
    out, used, first = [], {}, 0
    for content, n in bins:
        at, offset = 0, 0
        while at < len(content):
            size, copies = content[at], 1
            while at + copies < len(content) and content[at + copies] == size:
                copies += 1
            out.append((size, used.get(size, 0), n * copies, copies, first, offset))
            used[size] = used.get(size, 0) + n * copies
            at, offset = at + copies, offset + copies * size
        first += n
    return out


def pack(pieces: DataFrame, capacity: int = CAPACITY, rows_per_salt: int = 50_000) -> DataFrame:
    """pieces with sequence_id and offset; lengths must be 1 to capacity.

    The histogram and the slots are bounded by the capacity, so they go to the driver and back by broadcast. Ranks
    within a length are made in two steps, by salted groups of bounded size and the groups' running counts.
    """
    spark = pieces.sparkSession
    pieces = written(pieces, "pieces")
    found = pieces.groupBy("length").count().collect()  # at most `capacity` rows
    counts = {int(r["length"]): int(r["count"]) for r in found}
    table = slots(solve(counts, capacity))
    salts = max(8, -(-max(counts.values(), default=0) // rows_per_salt))
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("tie", "piece", F.lit(7)), F.lit(salts)))
    groups = salted.groupBy("length", "salt").count()
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    bases = groups.select("length", "salt", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "tie")
    ranked = salted.withColumn("inside", F.row_number().over(inside) - 1).join(bases, ["length", "salt"]).withColumn("rank", F.col("base") + F.col("inside"))
    places = spark.createDataFrame(table, "s_length long, s_rank long, s_ranks long, s_copies long, s_first long, s_offset long")
    hit = (F.col("length") == F.col("s_length")) & (F.col("rank") >= F.col("s_rank")) & (F.col("rank") < F.col("s_rank") + F.col("s_ranks"))
    step = F.col("rank") - F.col("s_rank")
    return ranked.join(F.broadcast(places), hit).select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("s_first") + F.floor(step / F.col("s_copies"))).cast("long").alias("sequence_id"),
        (F.col("s_offset") + F.pmod(step, F.col("s_copies")) * F.col("length")).cast("long").alias("offset"),
    )


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY) -> DataFrame:
    return pack(token_pieces(docs, tokenizer, capacity), capacity)
