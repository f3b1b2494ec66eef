"""Near-duplicate sets: equal ones collapse first, links between different ones are met through keys and verified, classes are their components."""

from __future__ import annotations

import pickle
from hashlib import blake2b, md5, sha256
from sys import intern
from types import SimpleNamespace
from uuid import uuid4

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import keys_of
from ..functions.similarity import jaccard
from ..sources.shared import opened, shared_folder, stored
from . import hits
from .pairs import SLACK

#: Rows signed at once, rows of a block, pairs held before they are compared, tokens of the sets that a worker keeps.
CHUNK, BLOCK, PAIRS, HELD = 256, 2048, 1 << 20, 1_000_000


def fingerprint(tokens: Column) -> Column:
    return F.sha2(F.array_join(F.array_sort(tokens), "\x1f"), 256)


def copies(sets: DataFrame) -> DataFrame:
    """(id, rep): each row's representative, the least id of the rows with an equal set. The minimum combines before it shuffles."""
    marked = sets.select("id", fingerprint(F.col("tokens")).alias("fp"))
    return marked.join(marked.groupBy("fp").agg(F.min("id").alias("rep")), "fp").select("id", "rep")


def _buckets(sets: DataFrame, k: int, tables: int) -> DataFrame:
    sized = keys_of(sets, k, tables).join(sets.select("id", F.size("tokens").alias("n")), "id")
    return sized.select(F.xxhash64("table_id", "bucket_key").alias("key"), "id", "n")


def _verified(met: DataFrame, sets: DataFrame, least: float) -> DataFrame:
    """met (id_a, id_b, …) with the exact similarity, where it is `least` or more: only met pairs read sets."""
    both = met.join(sets.select(F.col("id").alias("id_a"), F.col("tokens").alias("x")), "id_a").join(sets.select(F.col("id").alias("id_b"), F.col("tokens").alias("y")), "id_b")
    return both.withColumn("jaccard", F.round(jaccard(F.col("x"), F.col("y")), 6)).where(F.col("jaccard") >= least).drop("x", "y")


def _ends(line: str) -> list[str]:
    return line.split("\x1f")


def _runs(n: int):
    def parts(line: str) -> list[str]:
        w = line.split(" ")
        return [" ".join(x) for x in zip(*[w[i:] for i in range(n)], strict=False)] if len(w) >= n else [line]

    return parts


def _key_numbers(sig: np.ndarray, k: int, tables: int) -> np.ndarray:
    """[rows, tables] keys as numbers: up to two values lie side by side in 62 bits, more are hashed to 64."""
    parts = sig.reshape(len(sig), tables, k)
    if k <= 2:
        return parts[:, :, 0] if k == 1 else (parts[:, :, 0] << 31) | parts[:, :, 1]
    flat = [int.from_bytes(blake2b(x.tobytes(), digest_size=8).digest(), "big", signed=True) for x in parts.reshape(-1, k)]
    return np.array(flat, np.int64).reshape(len(sig), tables)


def _packed(lines: DataFrame, parts, k: int, tables: int) -> DataFrame:
    """(id, n, fp, keys, file, at, size) of lines (id, line): size and fingerprint of the set, its keys, and where the shared folder holds the compressed line; parts(line) gives the tokens."""
    folder = shared_folder(lines.sparkSession, "lines")

    def task(batches):
        import pyarrow as pa

        fs, inside = opened(folder)
        fs.create_dir(inside, recursive=True)
        path, at, codec = f"{folder}/{uuid4().hex}", 0, pa.Codec("zstd", 1)
        with fs.open_output_stream(opened(path)[1]) as out:
            for batch in batches:
                for begin in range(0, batch.num_rows, CHUNK):
                    own = batch.slice(begin, CHUNK)
                    held, prints, digests, places, sizes = [], [], [], [], []
                    for line in own.column("line").to_pylist():
                        tokens = sorted(set(parts(line)))
                        prints.append(sha256("\x1f".join(tokens).encode()).digest())
                        digests.append(b"".join([md5(t.encode()).digest() for t in tokens]))
                        raw = line.encode()
                        packed = len(raw).to_bytes(8, "little") + codec.compress(raw, asbytes=True)
                        out.write(packed)
                        places.append(at)
                        sizes.append(len(packed))
                        at += sizes[-1]
                        held.append(len(tokens))
                    # the first 28 bits of each digest are the token's number
                    number = (np.frombuffer(b"".join(digests), ">u4")[::4] >> 4).astype(np.int64)
                    bag = SimpleNamespace(n=len(held), row=np.repeat(np.arange(len(held)), held), code=slice(None))
                    keys = _key_numbers(hits.signature(bag, number, k * tables), k, tables)
                    yield pa.RecordBatch.from_arrays(
                        [own.column("id"), pa.array(held, pa.int64()), pa.array(prints, pa.binary()), pa.ListArray.from_arrays(pa.array(np.arange(len(held) + 1) * tables, pa.int32()), pa.array(keys.ravel())), pa.array([path] * len(held)), pa.array(places, pa.int64()), pa.array(sizes, pa.int64())],
                        names=["id", "n", "fp", "keys", "file", "at", "size"],
                    )

    return lines.select("id", "line").mapInArrow(task, "id long, n long, fp binary, keys array<long>, file string, at long, size long")


class _Lines:
    """Sets read from the shared folder; about HELD tokens of them stay."""

    def __init__(self, parts):
        self.parts, self.files, self.sets, self.tokens = parts, {}, {}, 0

    def get(self, file: str, at: int, size: int) -> set:
        import pyarrow as pa

        if (own := self.sets.get((file, at))) is None:
            if file not in self.files:
                fs, inside = opened(file)
                self.files[file] = fs.open_input_file(inside)
            raw = self.files[file].read_at(size, at)
            line = pa.Codec("zstd").decompress(raw[8:], int.from_bytes(raw[:8], "little"), asbytes=True).decode()
            own = set(map(intern, self.parts(line)))
            if self.tokens > HELD:
                self.sets, self.tokens = {}, 0
            self.sets[file, at] = own
            self.tokens += len(own)
        return own


class _Pairs:
    """Takes the counts of common keys; keeps pairs of an id and a greater one whose sizes allow `least`."""

    def __init__(self, ids: np.ndarray, n: np.ndarray, least: float):
        self.queries, self.n, self.least, self.found, self.held, self.block = ids, n, least - SLACK, [], 0, None

    def add(self, first: int, size: int, q: np.ndarray, row: np.ndarray, met: np.ndarray, ids: np.ndarray) -> None:
        q = q + first
        n, other = self.n[q], self.block["n"][row]
        keep = np.flatnonzero((self.queries[q] < ids[row]) & (n >= self.least * other) & (other >= self.least * n))
        if len(keep):
            row = row[keep]
            self.found.append((q[keep], ids[row], met[keep], other[keep], self.block["at"][row], self.block["size"][row], self.block["file"][row]))
            self.held += len(keep)

    def taken(self) -> list[np.ndarray]:
        """What is held, in the order of queries."""
        out = [np.concatenate(x) for x in zip(*self.found, strict=True)]
        self.found, self.held = [], 0
        order = np.argsort(out[0], kind="stable")
        return [x[order] for x in out]


def _columns_of(batch) -> dict:
    return {c: batch.column(c).to_numpy(zero_copy_only=False) for c in ("id", "n", "at", "size", "file")} | {"keys": batch.column("keys").flatten().to_numpy().reshape(batch.num_rows, -1)}


def _blocks_of(rows: DataFrame) -> str:
    """A shared folder with posting lists of the rows' keys, in blocks."""

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            for begin in range(0, batch.num_rows, BLOCK):
                x = _columns_of(batch.slice(begin, BLOCK))
                made = hits.posted(0, list(x.pop("keys").T.copy()), x.pop("id"), None) | x
                yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(made, 5)], pa.binary())], names=["block"])

    path = shared_folder(rows.sparkSession, "postings")
    rows.mapInArrow(task, "block binary").write.parquet(path)
    return path


def _met(rows: DataFrame, parts, least: float) -> DataFrame:
    """(id_a, id_b, hits, n_a, n_b, common) of the pairs that share a key and may reach `least`, counted inside the task that holds id_a: no pair is shuffled, and a set is read where a pair needs it."""
    folder = _blocks_of(rows)
    session = rows.sparkSession
    many = max(int(session.conf.get("spark.sql.shuffle.partitions")), 4 * session.sparkContext.defaultParallelism)

    def task(batches):
        import pyarrow as pa

        lines = _Lines(parts)
        for batch in batches:
            for begin in range(0, batch.num_rows, BLOCK):
                x = _columns_of(batch.slice(begin, BLOCK))
                asked, held = list(x["keys"].T.copy()), _Pairs(x["id"], x["n"], least)

                def checked(x=x, held=held):
                    q, ids, met, n, at, size, file = held.taken()
                    common, last, own = np.zeros(len(q), np.int64), -1, None
                    for i, (p, a, s, f) in enumerate(zip(q.tolist(), at.tolist(), size.tolist(), file, strict=True)):
                        if p != last:
                            last, own = p, lines.get(x["file"][p], int(x["at"][p]), int(x["size"][p]))
                        common[i] = len(own & lines.get(f, a, s))
                    keep = np.flatnonzero(common >= (least - SLACK) * (x["n"][q] + n - common))
                    return pa.RecordBatch.from_arrays([pa.array(v[keep].astype(np.int64)) for v in (x["id"][q], ids, met, x["n"][q], n, common)], names=["id_a", "id_b", "hits", "n_a", "n_b", "common"])

                for held.block in hits._blocks(folder):
                    hits._count(held.block, asked, [(None, held)])
                    if held.held > PAIRS:
                        yield checked()
                if held.held:
                    yield checked()

    near = rows.repartitionByRange(many, "root", "id").sortWithinPartitions("root", "id")
    return near.mapInArrow(task, "id_a long, id_b long, hits long, n_a long, n_b long, common long")


def _line_links(lines: DataFrame, parts, k: int, tables: int, least: float) -> DataFrame:
    rows = stored(_packed(lines, parts, k, tables), "sets")
    reps = rows.join(rows.groupBy("fp").agg(F.min("id").alias("id")).select("id"), "id", "left_semi").drop("fp")
    keyed = reps.select("id", F.posexplode("keys").alias("t", "key"))
    shared = keyed.groupBy("t", "key").agg(F.min("id").alias("root"), F.count("*").alias("c")).where("c > 1").drop("c")
    # what shares no key has no link; the least id that a set meets brings most of a family into one task
    root = keyed.join(shared, ["t", "key"]).groupBy("id").agg(F.min("root").alias("root"))
    found = _met(stored(reps.join(root, "id"), "meeting"), parts, least)
    return found.select("id_a", "id_b", "hits", F.round(F.col("common") / (F.col("n_a") + F.col("n_b") - F.col("common")), 6).alias("jaccard")).where(F.col("jaccard") >= least)


def links(sets: DataFrame, k: int, tables: int, least: float = 0.8) -> DataFrame:
    """(id_a, id_b, hits, jaccard) between representatives of different sets that share a key; every such link.

    Pairs are met and compared inside tasks; its size is that of the answer. For classes of large families use
    `classes`, which makes no pair within a part that is already known to hang together. Sets whose sizes exclude
    `least` are not compared.
    """
    return _line_links(sets.select("id", F.array_join("tokens", "\x1f").alias("line")), _ends, k, tables, least)


def text_links(texts: DataFrame, n: int, k: int, tables: int, least: float = 0.8) -> DataFrame:
    """`links` between the sets of runs of n words; texts is (id, line), a line its words with a blank between. Only lines are moved and stored, runs are made inside tasks."""
    return _line_links(texts, _runs(n), k, tables, least)


def components(edges: DataFrame) -> DataFrame:
    """(id, class_id): the least id of each component of edges (id_a, id_b), by rounds that link every node to its least neighbour.

    A round is two combinable minima and two joins; rounds grow with the logarithm of a component's diameter. Each round
    is written to the shared folder, so a lost executor costs one round. Only a count and a hash reach the driver.
    """
    now = edges.select(F.greatest("id_a", "id_b").alias("u"), F.least("id_a", "id_b").alias("v")).where("u <> v").distinct()
    now, before = stored(now, "edges"), None
    while True:
        digest = tuple(now.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.lit(0))).first())
        if digest == before:
            return now.groupBy(F.col("u").alias("id")).agg(F.min("v").alias("class_id")).unionByName(now.select(F.col("v").alias("id"), F.col("v").alias("class_id")).distinct())
        before = digest
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least("u", F.min("v")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = stored(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct(), "edges")


def classes(sets: DataFrame, k: int, tables: int, least: float = 0.8) -> DataFrame:
    """(id, class_id) for every row: the components of all links of `links`, without making all of a bucket's pairs.

    First each member of a bucket is compared with the bucket's least id; then only buckets that still hold several
    components pair their members, and only across components. The skipped pairs could join nothing new.
    """
    own = stored(copies(sets), "copies")
    reps = stored(sets.join(own.where("id = rep"), "id", "left_semi"), "representatives")
    b = stored(_buckets(reps, k, tables), "keys")
    star = b.join(b.groupBy("key").agg(F.min("id").alias("id_a")), "key").where("id <> id_a").select("id_a", F.col("id").alias("id_b")).distinct()
    near = stored(_verified(star, reps, least).select("id_a", "id_b"), "links")
    part = b.join(components(near), "id", "left").withColumn("class_id", F.coalesce("class_id", "id"))
    split = part.groupBy("key").agg(F.min("class_id").alias("lo"), F.max("class_id").alias("hi")).where("lo <> hi").select("key")
    part = stored(part.join(split, "key", "left_semi"), "parts")
    other = part.select("key", F.col("id").alias("id_b"), F.col("n").alias("n_b"), F.col("class_id").alias("class_b"))
    fits = (F.col("n") >= least * F.col("n_b")) & (F.col("n_b") >= least * F.col("n"))
    across = part.join(other, "key").where((F.col("class_id") < F.col("class_b")) & fits).select(F.col("id").alias("id_a"), "id_b").distinct()
    whole = components(near.unionByName(_verified(across, reps, least).select("id_a", "id_b")))
    return own.join(whole.withColumnRenamed("id", "rep"), "rep", "left").select("id", F.coalesce("class_id", "rep").alias("class_id"))
