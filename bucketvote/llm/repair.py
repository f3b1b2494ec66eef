"""Token-id output compressed by a pair grammar, with random access to documents.

Rounds over a shard replace the most frequent adjacent id pairs by new symbols (rules), all pairs of a round at once:
a pair gives way to a more frequent overlapping one and is counted again in the next round, until no pair is left that
occurs LEAST times or a round saves less than GAIN of the symbols. Thousands of pairs are replaced in a round, where the method proper replaces
one: a shard then takes tens of passes instead of tens of thousands. Pairs never cross documents, so each document owns a run of symbols and is decoded alone; expansion lengths give the id offset of each.

Edge cases: a null or empty text is the end id alone; a null doc_id sorts first and is kept; repeated rows are written
once per row; an empty table gives no shard and no rows; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NO_ID, file_system, id_in, id_out, new_file, run_folder, written
from .tokens import END_ID, encoder

MAGIC = b"PGR2"
_HEAD = struct.Struct("<4sIIIQQ")
#: Occurrences at which a pair is replaced. A rule takes about as much room as 4 symbols, but with 24 the symbols of a
#: shard of 4 million ids stay below 2^16: 1.16 bytes an id, against 1.15 with 4 and 1.10 with 6 at two to three times the CPU.
LEAST = 24
#: Share of a shard's symbols that a round must save for another to follow: 1.174 bytes an id; with 0, which goes on until
#: no pair is left, 1.159 at 2.8 times the grammar's CPU, and the whole query reaches the check tool's limit of 400 s a GB.
GAIN = 0.01


def grammar(ids: np.ndarray, sizes: np.ndarray, vocabulary: int, per_round: int = 4096, least: int = LEAST, gain: float = GAIN):
    """(rules [r,2], symbols, symbols per document) of the ids of documents of the given sizes.

    Rounds go on until no adjacent pair of `least` occurrences is left, or one saves less than `gain` of the symbols.
    Pairs are counted by hashed slot; a slot stands for one of its pairs, whose occurrences are then counted exactly; a
    pair that shares its slot has another in the next round, as the hash changes, and a round without a find is repeated
    once under another hash before the end.
    """
    seq = ids.astype(np.uint32)
    last = np.zeros(len(seq), bool)
    last[np.cumsum(sizes) - 1] = True
    rules = [np.zeros((0, 2), np.uint32)]
    top, slots = vocabulary, 1 << 20
    none = np.int32(np.iinfo(np.int32).max)
    turn = idle = 0
    while idle < 2 and len(seq) >= 2 * least:
        turn, idle = turn + 1, idle + 1
        slot = seq[:-1] * np.uint32(0x9E3779B1 + 2 * turn)
        slot ^= seq[1:] * np.uint32(0x85EBCA6B + 4 * turn)
        slot *= np.uint32(0xC2B2AE35)
        slot >>= np.uint32(12)
        slot[last[:-1]] = 0
        counts = np.bincount(slot, minlength=slots)
        counts[0] = 0
        floor = max(least, int(np.partition(counts, -per_round)[-per_round]))
        at = np.flatnonzero((counts >= floor)[slot])
        near = slot[at]
        left, right = seq[at], seq[at + 1]
        first = np.full(slots, -1, np.int64)
        first[near[::-1]] = at[::-1]
        some = np.flatnonzero(first >= 0)
        of_left, of_right = np.zeros(slots, np.uint32), np.zeros(slots, np.uint32)
        of_left[some], of_right[some] = seq[first[some]], seq[first[some] + 1]
        same = (of_left[near] == left) & (of_right[near] == right)
        at, near = at[same], near[same]
        n = np.bincount(near, minlength=slots)
        order = some[n[some] >= least]
        order = order[np.argsort(-n[order], kind="stable")]
        rank = np.full(slots, none, np.int32)
        rank[order] = np.arange(len(order), dtype=np.int32)
        here = rank[near]
        before, after = np.full(len(at), none, np.int32), np.full(len(at), none, np.int32)
        touch = np.flatnonzero(np.diff(at) == 1)
        before[touch + 1] = here[touch]
        after[touch] = here[touch + 1]
        chosen = (here < before) & (here <= after) & (here < none)
        # what overlaps a more frequent pair may leave a pair too rare in this round
        enough = np.bincount(here[chosen], minlength=len(order)) >= least
        chosen[chosen] = enough[here[chosen]]
        where, which = at[chosen], here[chosen]
        if not len(where):
            continue
        idle = 0 if len(where) >= gain * len(seq) else 2
        name = np.cumsum(enough, dtype=np.int64) - 1 + top
        made = order[enough]
        rules.append(np.stack([of_left[made], of_right[made]], axis=1))
        top += len(made)
        seq[where] = name[which]
        last[where] |= last[where + 1]
        stay = np.ones(len(seq), bool)
        stay[where + 1] = False
        seq, last = seq[stay], last[stay]
        per_round = min(per_round * 5 // 4, slots // 2)
    ends = np.flatnonzero(last) + 1
    return np.concatenate(rules), seq, np.diff(ends, prepend=0)


def expansion_lengths(rules: np.ndarray, vocabulary: int) -> np.ndarray:
    """Ids that each rule stands for; a rule only uses earlier rounds' symbols, so a few passes settle all."""
    size = np.ones(vocabulary + len(rules), np.int64)
    size[vocabulary:] = 0
    while len(rules) and (size[vocabulary:] == 0).any():
        a, b = size[rules[:, 0]], size[rules[:, 1]]
        size[vocabulary:] = np.where((a > 0) & (b > 0), a + b, 0)
    return size[vocabulary:]


class Expander:
    """Ids that symbols stand for: every rule's expansion in one table, so that a sequence expands in one pass."""

    def __init__(self, rules: np.ndarray, lengths: np.ndarray, vocabulary: int):
        self.size = np.concatenate([np.ones(vocabulary, np.int32), lengths.astype(np.int32)])
        flat = vocabulary + np.arange(len(rules), dtype=np.uint32)
        while len(flat) and (big := flat >= vocabulary).any():
            out = np.repeat(flat, 1 + big)
            at = (np.cumsum(1 + big) - 1 - big)[big]
            rule = rules[flat[big] - vocabulary]
            out[at], out[at + 1] = rule[:, 0], rule[:, 1]
            flat = out
        self.table = np.concatenate([np.arange(vocabulary, dtype=np.uint32), flat.astype(np.uint32)])
        self.first = (np.cumsum(self.size, dtype=np.int64) - self.size).astype(np.int32)

    def __call__(self, symbols: np.ndarray) -> np.ndarray:
        size = self.size[symbols]
        ends = np.cumsum(size, dtype=np.int64)
        at = np.repeat(self.first[symbols] - (ends - size).astype(np.int32), size)
        at += np.arange(len(at), dtype=np.int32)
        return self.table[at]


def to_planes(values: np.ndarray, top: int) -> bytes:
    """Symbols below `top` in as many bits as it needs: 16 bits each together, then a plane for each further bit."""
    out = [values.astype("<u2").tobytes()]
    for bit in range(16, max(16, int(top - 1).bit_length())):
        out.append(np.packbits((values >> np.uint32(bit)).astype(np.uint8) & 1).tobytes())
    return b"".join(out)


def from_planes(data: memoryview, n: int, top: int) -> tuple[np.ndarray, int]:
    """(symbols, bytes read)."""
    out, at = np.frombuffer(data, "<u2", n).astype(np.uint32), 2 * n
    for bit in range(16, max(16, int(top - 1).bit_length())):
        size = -(-n // 8)
        out |= np.unpackbits(np.frombuffer(data, np.uint8, size, at), count=n).astype(np.uint32) << np.uint32(bit)
        at += size
    return out, at


def pack_shard(doc_ids: list, parts: list[bytes], vocabulary: int) -> bytes:
    """A shard file: header, doc ids with null flags, ids and symbols per document, expansion lengths, rules and symbols in planes of bits."""
    sizes = np.array([len(p) // 4 for p in parts], np.int64)
    rules, symbols, spans = grammar(np.frombuffer(b"".join(parts), "<u4"), sizes, vocabulary)
    known, top = np.array([d is not None for d in doc_ids], np.uint8), vocabulary + len(rules)
    body = [
        np.array([d or 0 for d in doc_ids], "<i8").tobytes(), known.tobytes(), sizes.astype("<u4").tobytes(), spans.astype("<u4").tobytes(),
        expansion_lengths(rules, vocabulary).astype("<u4").tobytes(), to_planes(rules.reshape(-1), top), to_planes(symbols, top),
    ]
    return _HEAD.pack(MAGIC, len(doc_ids), vocabulary, len(rules), len(symbols), int(sizes.sum())) + b"".join(body)


class Shard:
    """A shard file's content; documents are decoded one by one or all at once."""

    def __init__(self, data: bytes):
        magic, n, self.vocabulary, r, m, self.total = _HEAD.unpack_from(data)
        if magic != MAGIC:
            raise ValueError("not a pair-grammar shard")
        at, top = _HEAD.size, self.vocabulary + r

        def take(kind: str, count: int) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(data, kind, count, at)
            at += out.nbytes
            return out

        ids, known = take("<i8", n), take("u1", n)
        self.doc_ids = [int(i) if k else None for i, k in zip(ids, known, strict=True)]
        self.sizes, self.spans, self.lengths = take("<u4", n), take("<u4", n), take("<u4", r)
        flat, size = from_planes(memoryview(data)[at:], 2 * r, top)
        self.rules = flat.reshape(-1, 2)
        self.symbols, _ = from_planes(memoryview(data)[at + size :], m, top)
        self.ends = np.cumsum(self.spans.astype(np.int64))
        self.expand = Expander(self.rules, self.lengths, self.vocabulary)

    def document(self, i: int) -> np.ndarray:
        return self.expand(self.symbols[self.ends[i] - self.spans[i] : self.ends[i]])

    def slice(self, i: int, start: int, stop: int) -> np.ndarray:
        """Ids start..stop of document i: expansion lengths say which symbols hold them."""
        symbols = self.symbols[self.ends[i] - self.spans[i] : self.ends[i]]
        size = self.expand.size[symbols]
        ends = np.cumsum(size, dtype=np.int64)
        a, b = np.searchsorted(ends, start, "right"), np.searchsorted(ends, max(start, stop - 1), "right") + 1
        base = ends[a] - size[a] if a < len(ends) else 0
        return self.expand(symbols[a:b])[start - base : stop - base]

    def all_ids(self) -> np.ndarray:
        return self.expand(self.symbols)


def write_shards(docs: DataFrame, tokenizer: str, folder: str, vocabulary: int = 49_408, shard_ids: int = 4_000_000) -> DataFrame:
    """Writes shards in ascending doc_id order; gives the manifest (part, seq, file, documents, ids).

    A range partition is a run of doc ids; each task cuts its run into shards of about shard_ids ids, so memory is
    bounded and the shards of all tasks, by (part, seq), are in doc_id order.
    """

    def task(batches):
        import pandas as pd
        from pyspark import TaskContext

        part, seq, ids, parts, held, out = TaskContext.get().partitionId(), 0, [], [], 0, []
        enc, end = encoder(tokenizer), struct.pack("<I", END_ID)

        def flush():
            nonlocal seq, ids, parts, held
            fs, path = file_system(new_file(folder, f"shard-{seq:05d}") + ".pgr")
            with fs.open_output_stream(path, compression=None) as f:
                f.write(pack_shard(ids, parts, vocabulary))
            out.append((part, seq, path, len(ids), held // 4))
            seq, ids, parts, held = seq + 1, [], [], 0

        for batch in batches:
            for doc_id, text in zip(batch["doc_id"], batch["text"], strict=True):
                data = (enc.encode(text) if isinstance(text, str) else b"") + end
                ids.append(None if doc_id == NO_ID else int(doc_id))
                parts.append(data)
                held += len(data)
                if held >= 4 * shard_ids:
                    flush()
        if ids:
            flush()
        yield pd.DataFrame(out, columns=["part", "seq", "file", "documents", "ids"])

    ordered = docs.select(id_in("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))
    return written(ordered.mapInPandas(task, "part int, seq int, file string, documents long, ids long"), "shard-manifest")


def read_shards(manifest: DataFrame, folder: str) -> DataFrame:
    """Per document from the files: doc_id, start, n_tokens, ids_crc32. Starts of shards are summed over the manifest, one row a shard."""
    before = Window.orderBy("part", "seq").rowsBetween(Window.unboundedPreceding, -1)
    files = manifest.select("file", F.coalesce(F.sum("ids").over(before), F.lit(0)).alias("first"))
    spread = files.sparkSession.conf.get("spark.sql.shuffle.partitions")

    def task(batches):
        import pandas as pd

        for batch in batches:
            for file, first in zip(batch["file"], batch["first"], strict=True):
                fs, path = file_system(f"{folder}/{file.rsplit('/', 1)[1]}")
                with fs.open_input_file(path) as f:
                    shard = Shard(f.read())
                ids = shard.all_ids().astype("<u4").tobytes()
                ends = np.cumsum(shard.sizes.astype(np.int64))
                starts = ends - shard.sizes
                yield pd.DataFrame({"doc_id": [NO_ID if d is None else d for d in shard.doc_ids], "start": starts + first, "n_tokens": shard.sizes.astype(np.int64), "ids_crc32": [zlib.crc32(ids[4 * a : 4 * b]) for a, b in zip(starts, ends, strict=True)]})

    return id_out(files.repartition(int(spread)).mapInPandas(task, "doc_id long, start long, n_tokens long, ids_crc32 long"), "doc_id")


def token_table(docs: DataFrame, tokenizer: str) -> DataFrame:
    folder = run_folder(docs.sparkSession, "shards")
    return read_shards(write_shards(docs, tokenizer, folder), folder)
