"""Lines repeated across documents: range-partitioned hashes, read in order, give each document a bitmap of kept lines.

A line's key is the line stripped of ASCII white space, A-Z lowered. Long keys in many documents lose all their lines
but those of the largest doc_id that holds them. Hashes are range-partitioned by (hash, doc_id), so the lines of a very
common key spread over many tasks; within a partition they are sorted by document, last first, and position, and
streamed. A key that crosses a partition's edge is settled by summing its pieces, two a partition at most.

Edge cases: a null or empty text is one empty line; a null doc_id counts as the smallest id, as one document; rows of
one doc_id count as one document, and each row gets the bitmap of its own text; ties do not arise, as equal keys of one
document share their fate; an empty table gives no rows; other columns are kept by `apply` and ignored otherwise.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NO_ID, WHITE, id_out, lean, with_facts, written

LEAST_CHARS, LEAST_DOCS = 40, 5
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_FOLD = str.maketrans(_UPPER, _LOWER)


def line_key(line: str) -> str:
    return line.strip(WHITE).translate(_FOLD)


def keyed_lines(docs: DataFrame, least_chars: int = LEAST_CHARS) -> DataFrame:
    """(hi, lo, doc, row_key, pos) of lines with keys of enough code points; 128 bits of hash stand for a key."""
    lines = docs.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc"), F.xxhash64("text").alias("row_key"), F.posexplode(F.split(F.col("text"), "\n")).alias("pos", "line"))
    keys = lines.select("doc", "row_key", "pos", F.translate(F.trim("line", F.lit(WHITE)), _UPPER, _LOWER).alias("key"))
    return keys.where(F.length("key") >= least_chars).select(F.xxhash64("key").alias("hi"), F.xxhash64(F.lit(0x5EED), "key", F.lit(1)).alias("lo"), "doc", "row_key", "pos")


def dropped_lines(lines: DataFrame, least_docs: int = LEAST_DOCS) -> DataFrame:
    """(doc, row_key, pos) of the lines to drop."""
    # hashes are stored first: the bounds of the ranges are sampled from them, not from texts read and hashed once more
    ordered = written(lines, "line-hashes").repartitionByRange("hi", "lo", F.desc("doc")).sortWithinPartitions("hi", "lo", F.desc("doc"), "pos")
    kinds = "kind int, hi long, lo long, doc long, row_key long, pos int, docs long"

    def decide(block: np.ndarray, docs: int):
        """Rows of a whole run, documents in falling order: all but the first document's go."""
        return block[block["doc"] != block["doc"][0]] if docs >= least_docs else block[:0]

    def task(frames):
        """Kind 0: dropped. Kind 1: waits for the whole of a run that touches an edge. Kind 2: such a run's piece, its first document in doc, its number of documents in docs."""
        import pandas as pd

        held = None  # rows of the run that is still open, as blocks; a long run gives its rows away as waiting
        first_run = True

        def frame(kind, b, docs=0):
            return pd.DataFrame({"kind": np.full(len(b), kind, np.int32), "hi": b["hi"], "lo": b["lo"], "doc": b["doc"], "row_key": b["row_key"], "pos": b["pos"], "docs": np.full(len(b), docs, np.int64)})

        kind_of = np.dtype([("hi", "<i8"), ("lo", "<i8"), ("doc", "<i8"), ("row_key", "<i8"), ("pos", "<i4")])

        def close(run, edge):
            blocks, docs, gave = run["blocks"], run["docs"], run["gave"]
            rows = np.concatenate(blocks) if blocks else np.zeros(0, kind_of)
            if edge or gave:
                head = np.zeros(1, kind_of)
                head["hi"], head["lo"], head["doc"] = run["hi"], run["lo"], run["top"]
                out = [frame(2, head, docs)]
                return ([frame(1, rows)] if len(rows) else []) + out
            gone = decide(rows, docs)
            return [frame(0, gone)] if len(gone) else []

        for pdf in frames:
            if not len(pdf):
                continue
            b = np.zeros(len(pdf), kind_of)
            for c in kind_of.names:
                b[c] = pdf[c].to_numpy()
            new_key = np.flatnonzero((np.diff(b["hi"]) != 0) | (np.diff(b["lo"]) != 0)) + 1
            new_doc = np.ones(len(b), bool)
            new_doc[1:] = (np.diff(b["doc"]) != 0) | (np.diff(b["hi"]) != 0) | (np.diff(b["lo"]) != 0)
            seen = np.cumsum(new_doc)
            bounds = [0, *new_key.tolist(), len(b)]
            out = []
            # runs that lie inside the batch are settled together
            starts, stops = np.array(bounds[:-1]), np.array(bounds[1:])
            n_docs = seen[stops - 1] - seen[starts] + 1
            inner = np.ones(len(starts), bool)
            inner[0] = inner[-1] = False
            hot = np.flatnonzero(inner & (n_docs >= least_docs))
            if len(hot):
                at = np.concatenate([np.arange(starts[h], stops[h]) for h in hot])
                top = np.repeat(b["doc"][starts[hot]], stops[hot] - starts[hot])
                gone = b[at][b["doc"][at] != top]
                if len(gone):
                    out.append(frame(0, gone))
            for i in sorted({0, len(starts) - 1}):
                rows = b[starts[i] : stops[i]]
                hi, lo = int(rows["hi"][0]), int(rows["lo"][0])
                if held is not None and (held["hi"], held["lo"]) == (hi, lo):
                    held["docs"] += int(n_docs[i]) - (held["last"] == int(rows["doc"][0]))
                else:
                    if held is not None:
                        out += close(held, held["edge"])
                    held = {"hi": hi, "lo": lo, "top": int(rows["doc"][0]), "docs": int(n_docs[i]), "blocks": [], "gave": False, "edge": first_run}
                    first_run = False
                held["last"] = int(rows["doc"][-1])
                held["blocks"].append(rows)
                if sum(map(len, held["blocks"])) > 200_000:  # bounded memory: the rows wait, as if at an edge
                    out.append(frame(1, np.concatenate(held["blocks"])))
                    held["blocks"], held["gave"] = [], True
            if out:
                yield pd.concat(out)
        if held is not None:
            yield pd.concat(close(held, True))

    found = written(ordered.mapInPandas(lean(task), kinds), "line-runs")
    edges = found.where("kind = 2").groupBy("hi", "lo").agg(F.max("doc").alias("top"), F.sum("docs").alias("n")).where(F.col("n") >= least_docs)
    waiting = with_facts(found.where("kind = 1").select("hi", "lo", "doc", "row_key", "pos"), edges, "hi", "lo").where("doc <> top").select("doc", "row_key", "pos")
    return found.where("kind = 0").select("doc", "row_key", "pos").unionByName(waiting)


def line_mask(gone) -> bytes:
    """Compressed bitmap of the lines to drop, a bit a line up to the last of them: later lines stay."""
    at = np.asarray(gone, np.int64)
    mask = np.zeros(int(at.max()) + 1 if len(at) else 0, bool)
    mask[at] = True
    return zlib.compress(np.packbits(mask).tobytes(), 1)


def kept_lines(text: str, mask: bytes) -> str:
    drop = np.unpackbits(np.frombuffer(zlib.decompress(mask), np.uint8)).tolist()
    lines = text.split("\n")
    return "\n".join([line for line, d in zip(lines, drop, strict=False) if not d] + lines[len(drop) :])


def bitmaps(docs: DataFrame, least_chars: int = LEAST_CHARS, least_docs: int = LEAST_DOCS) -> DataFrame:
    """A written table (doc, row_key, n_dropped, mask) of the texts that lose lines: no text is shuffled or returned.

    doc is doc_id, or NO_ID for null; row_key is xxhash64 of the text, so that rows that share an id have masks of their own.
    """
    gone = dropped_lines(keyed_lines(docs, least_chars), least_docs).groupBy("doc", "row_key").agg(F.collect_set("pos").alias("gone"))

    def task(frames):
        for f in frames:
            f["n_dropped"] = [len(g) for g in f["gone"]]
            f["mask"] = [line_mask(g) for g in f["gone"]]
            yield f.drop(columns="gone")

    return written(gone.mapInPandas(lean(task), "doc long, row_key long, n_dropped long, mask binary"), "line-masks")


def _masked(docs: DataFrame, found: DataFrame) -> DataFrame:
    """(row, doc, text, n_dropped, mask): each row of docs as a struct, whatever its columns' names, beside its mask or null."""
    row = F.struct(*docs.columns)
    rows = docs.select(row.alias("row"), F.coalesce("doc_id", F.lit(NO_ID)).alias("doc"), F.xxhash64("text").alias("row_key"))
    return rows.join(found, ["doc", "row_key"], "left")


def apply(docs: DataFrame, least_chars: int = LEAST_CHARS, least_docs: int = LEAST_DOCS) -> DataFrame:
    """docs with the dropped lines gone from text, in docs' columns whatever their names; texts that lose none, null ones too, stay as they are. n_chars follows where there is one."""

    @F.pandas_udf("string")
    def kept(text, mask):
        import pandas as pd

        return pd.Series([t if m is None else kept_lines(t, m) for t, m in zip(text, mask, strict=True)], dtype=object)

    joined = _masked(docs, bitmaps(docs, least_chars, least_docs)).withColumn("kept", kept(F.col("row.text"), F.col("mask")))
    columns = {c: F.col("row").getField(c) for c in docs.columns}
    columns["text"] = F.col("kept")
    if "n_chars" in columns:
        columns["n_chars"] = F.when(F.col("mask").isNull(), columns["n_chars"]).otherwise(F.length("kept").cast(docs.schema["n_chars"].dataType))
    return joined.select(*[c.alias(name) for name, c in columns.items()])


def digests(docs: DataFrame, least_chars: int = LEAST_CHARS, least_docs: int = LEAST_DOCS) -> DataFrame:
    """Per document row: doc_id, n_lines, n_dropped, kept_sha256 of the kept lines, by the stored bitmaps."""
    slim = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    joined = _masked(slim, bitmaps(slim, least_chars, least_docs)).select(F.col("doc").alias("doc_id"), F.col("row.text").alias("text"), F.coalesce("n_dropped", F.lit(0)).alias("n_dropped"), "mask")

    def task(frames):
        import pandas as pd

        for f in frames:
            rows = []
            for doc_id, text, dropped, mask in zip(f["doc_id"], f["text"], f["n_dropped"], f["mask"], strict=True):
                kept = text if mask is None else kept_lines(text, mask)
                rows.append((doc_id, text.count("\n") + 1, dropped, hashlib.sha256(kept.encode()).hexdigest()))
            yield pd.DataFrame(rows, columns=["doc_id", "n_lines", "n_dropped", "kept_sha256"])

    return id_out(joined.mapInPandas(lean(task), "doc_id long, n_lines long, n_dropped long, kept_sha256 string"), "doc_id")
