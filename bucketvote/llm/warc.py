"""WARC archives as seekable Zstandard bundles: independent frames of records, a seek table at the end, a record index.

Equal payloads of enough bytes are stored once: the row of largest page_id is the response, the others are revisit
records that refer to it. Each task writes bundles of its rows; every frame holds whole records and is decompressed
alone; the footer is the seek table of Zstandard's seekable format, and the index maps record ids to frame and offset.

Edge cases: a null html is an empty payload; a null page_id loses to any other and is written without one; rows that
share the largest page_id and payload are all responses; line breaks in a url are coded; a null url is left out; an
empty table gives no archive and no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NO_ID, file_system, id_in, id_out, new_file, run_folder, with_facts, written

LEAST = 1000
FRAME, BUNDLE = 256 << 10, 64 << 20
#: Fixed values of the seekable format.
SKIPPABLE, FOOTER = 0x184D2A5E, 0x8F92EAB1
_INDEX = "file string, record_id string, page_id long, frame long, offset long, length long"


def record_id(page_id: int, digest: str) -> str:
    return f"<urn:uuid:{uuid.UUID(bytes=hashlib.sha1(f'{page_id}/{digest}'.encode()).digest()[:16], version=5)}>"


def record(page_id: int, url: str | None, payload: bytes, digest: str, refers_to: int | None, date: str = "2024-01-01T00:00:00Z") -> bytes:
    """A response record, or a revisit record without the payload if refers_to is given."""
    kind = "response" if refers_to is None else "revisit"
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block += payload if refers_to is None else b""
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id(page_id, digest)}", f"WARC-Date: {date}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}"]
    if page_id != NO_ID:
        head.append(f"X-Page-Id: {page_id}")
    if url is not None:
        head.append("WARC-Target-URI: " + url.replace("%", "%25").replace("\r", "%0D").replace("\n", "%0A"))
    if refers_to is not None:
        head += [f"WARC-Refers-To: {record_id(refers_to, digest)}", f"X-Refers-To-Page: {refers_to}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    head += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(data: bytes, at: int = 0) -> tuple[dict[str, str], bytes, int]:
    """(headers, block, end) of the record at an offset."""
    stop = data.index(b"\r\n\r\n", at)
    lines = data[at:stop].decode().split("\r\n")
    if lines[0] != "WARC/1.1":
        raise ValueError("no WARC record here")
    headers = dict(line.split(": ", 1) for line in lines[1:])
    first = stop + 4
    last = first + int(headers["Content-Length"])
    if data[last : last + 4] != b"\r\n\r\n":
        raise ValueError("a record does not end where it says")
    return headers, data[first:last], last + 4


class BundleWriter:
    """Compresses records in independent frames and keeps the seek table and the index."""

    def __init__(self, out, level: int = 3, frame: int = FRAME):
        import zstandard

        self.out, self.limit = out, frame
        self.zip = zstandard.ZstdCompressor(level=level, write_content_size=True, write_checksum=True)
        self.held: list[bytes] = []
        self.size = self.total = 0
        self.table: list[tuple[int, int]] = []

    def add(self, data: bytes) -> tuple[int, int, int]:
        """(frame, offset in it, length) of the record."""
        if self.size and self.size + len(data) > self.limit:
            self.flush()
        place = len(self.table), self.size, len(data)
        self.held.append(data)
        self.size += len(data)
        self.total += len(data)
        return place

    def flush(self) -> None:
        if self.held:
            packed = self.zip.compress(b"".join(self.held))
            self.out.write(packed)
            self.table.append((len(packed), self.size))
            self.held, self.size = [], 0

    def close(self) -> None:
        self.flush()
        body = b"".join(struct.pack("<II", *x) for x in self.table) + struct.pack("<IBI", len(self.table), 0, FOOTER)
        self.out.write(struct.pack("<II", SKIPPABLE, len(body)) + body)
        self.out.close()


class BundleReader:
    """Frames of an open bundle by number, through its seek table."""

    def __init__(self, f, size: int):
        import zstandard

        self.f, self.zip = f, zstandard.ZstdDecompressor()
        f.seek(size - 9)
        n, flags, magic = struct.unpack("<IBI", f.read(9))
        if magic != FOOTER or flags & 0x80:
            raise ValueError("no seek table of this profile")
        f.seek(size - 9 - 8 * n)
        self.table = list(struct.iter_unpack("<II", f.read(8 * n)))
        self.starts = [0]
        for packed, _ in self.table:
            self.starts.append(self.starts[-1] + packed)

    def frame(self, i: int) -> bytes:
        self.f.seek(self.starts[i])
        data = self.zip.decompress(self.f.read(self.table[i][0]))
        if len(data) != self.table[i][1]:
            raise ValueError("a frame's size is not that of the seek table")
        return data

    def record(self, frame: int, offset: int) -> tuple[dict[str, str], bytes]:
        return parse(self.frame(frame), offset)[:2]


def plan(pages: DataFrame, least: int = LEAST) -> DataFrame:
    """(page_id, url, payload, digest, refers_to) per row.

    Responses are chosen on (page_id, digest) alone; the choice then meets the payloads by both, so equal payloads do not
    gather in one task.
    """
    rows = pages.select(id_in("page_id"), "url", F.coalesce("html", F.lit("")).cast("binary").alias("payload")).withColumn("digest", F.sha1("payload"))
    ids = written(rows.where(F.length("payload") >= least).select("page_id", "digest"), "digests")
    long_ = written(ids.groupBy("digest").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1"), "equal-payloads")
    revisits = with_facts(ids, long_, "digest").where("refers_to > page_id").select("page_id", "digest", "refers_to").distinct()
    return rows.join(revisits, ["page_id", "digest"], "left").select("page_id", "url", "payload", "digest", "refers_to")


def write(planned: DataFrame, folder: str) -> DataFrame:
    """Writes bundles; gives the written index (file, record_id, page_id, frame, offset, length), a row per record."""

    def task(frames):
        import pandas as pd

        writer, path, part = None, "", 0
        for f in frames:
            out = []
            refers = f["refers_to"].where(f["refers_to"].notna(), None) if f["refers_to"].isna().any() else f["refers_to"]
            for page_id, url, payload, digest, first in zip(f["page_id"], f["url"], f["payload"], f["digest"], refers, strict=True):
                if writer is None:
                    fs, path = file_system(new_file(folder, f"bundle-{part:04d}") + ".warc.zst")
                    writer, part = BundleWriter(fs.open_output_stream(path, compression=None)), part + 1
                data = record(int(page_id), url, bytes(payload), digest, None if first is None else int(first))
                out.append((path.rsplit("/", 1)[1], record_id(int(page_id), digest), page_id, *writer.add(data)))
                if writer.total >= BUNDLE:
                    writer.close()
                    writer = None
            yield pd.DataFrame(out, columns=["file", "record_id", "page_id", "frame", "offset", "length"])
        if writer is not None:
            writer.close()

    exact = planned.withColumn("refers_to", F.col("refers_to").cast("string"))
    return written(exact.mapInPandas(task, _INDEX), "warc-index")


def read(index: DataFrame, folder: str) -> DataFrame:
    """Reads all bundles of an index back: page_id, payload_bytes, payload_digest, record_type, refers_to.

    A response's digest and size are those of the payload read; a revisit's are those its headers give.
    """
    files = index.groupBy("file").agg(F.count("*").alias("records"))
    spread = int(index.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def task(frames):
        import pandas as pd

        for f in frames:
            for name, expected in zip(f["file"], f["records"], strict=True):
                fs, path = file_system(f"{folder}/{name}")
                seen = 0
                with fs.open_input_file(path) as handle:
                    bundle = BundleReader(handle, handle.size())
                    for i in range(len(bundle.table)):
                        data, at, out = bundle.frame(i), 0, []
                        while at < len(data):
                            h, block, at = parse(data, at)
                            digest, size = h["WARC-Payload-Digest"].removeprefix("sha1:"), int(h["X-Payload-Length"])
                            if h["WARC-Type"] == "response":
                                payload = block[block.index(b"\r\n\r\n") + 4 :]
                                if hashlib.sha1(payload).hexdigest() != digest or len(payload) != size:
                                    raise ValueError("a payload is not that of its digest")
                            out.append((int(h.get("X-Page-Id", NO_ID)), size, digest, h["WARC-Type"], int(h.get("X-Refers-To-Page", NO_ID))))
                        seen += len(out)
                        yield pd.DataFrame(out, columns=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])
                if seen != expected:
                    raise ValueError(f"{expected} records expected in {name}, {seen} read")

    back = files.repartition(spread).mapInPandas(task, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")
    return id_out(id_out(back, "page_id"), "refers_to")


def round_trip(pages: DataFrame, least: int = LEAST) -> DataFrame:
    folder = run_folder(pages.sparkSession, "warc")
    return read(write(plan(pages, least), folder), folder)
