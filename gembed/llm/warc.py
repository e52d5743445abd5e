"""Operator 5: WARC archives with a two-level capture index.

Records are written one gzip member each, so a record can be read alone by offset and length. The
index holds one line per record under its reversed-host URL key; lines are sorted over all shards and
packed into compressed blocks, and a sparse directory holds each block's first key, file, offset and
length. The directory lies in one sorted file per index file; a look-up bisects those files' first keys
(one per task that wrote the index, so a short list), reads one file, bisects its blocks, fetches one
block, bisects its lines, and fetches the record's byte range.

Records with equal payloads: that of the largest page id is a response, the others revisit it; payloads
under ``min_bytes`` bytes are all responses. Which page that is comes from an aggregate on the digest
(pre-aggregated, so a payload that a third of all pages share is one row per task), joined back by page.

Files carry a name unique to the attempt that wrote them, and readers go by the returned tables only.
Defined results: null html is the empty payload, null url the empty key; rows that repeat page id and
payload get a record each, of the same type; an empty table gives an empty archive and table; other
columns are ignored.
"""

from __future__ import annotations

import base64
import bisect
import gzip
import hashlib
import json
import re
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import file_system, mapped, scratch, stored

#: Index lines per compressed block, and bytes after which a new archive file begins.
BLOCK_LINES = 3000
FILE_BYTES = 256 << 20
DATE = "2024-01-01T00:00:00Z"
_RECORD = "page_id long, url string, key string, file string, offset long, length long"


def url_key(url: str | None) -> str:
    """Reversed host, port, then path and query, lower case, without scheme and fragment."""
    m = re.match(r"(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)(:[0-9]+)?([^#]*)", url or "")
    if not m:
        return (url or "").split("#")[0].lower().replace(" ", "%20").replace("\n", "%0A")
    host = re.sub(r"^www[0-9]*\.", "", m[1].lower())
    key = ",".join(reversed(host.split("."))) + (m[2] or "") + ")" + (m[3] or "/").lower()
    return key.replace(" ", "%20").replace("\n", "%0A")  # an index line ends its key with a space


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_bytes(page_id, url: str | None, payload: bytes, refers_to=None) -> bytes:
    """One uncompressed record; a revisit has the headers of its page and no payload."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    uri = re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url or "")
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{page_id}>", f"WARC-Date: {DATE}"]
    head += [f"WARC-Target-URI: {uri}"] * bool(uri)
    head += [f"WARC-Payload-Digest: sha1:{payload_digest(payload)}", "Content-Type: application/http; msgtype=response"]
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    body = http if refers_to is not None else http + payload
    head.append(f"Content-Length: {len(body)}")
    return "\r\n".join(head).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse_record(data: bytes) -> dict:
    """Headers and payload of one uncompressed record."""
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = dict(line.split(": ", 1) for line in lines[1:])
    body = rest[: int(fields["Content-Length"])]
    if rest[len(body) :] != b"\r\n\r\n":
        raise ValueError("record is cut short")
    return {"fields": fields, "payload": body.partition(b"\r\n\r\n")[2]}


def _page(urn: str | None) -> int | None:
    found = urn[len("<urn:page:") : -1] if urn else "None"
    return None if found == "None" else int(found)


@dataclass
class Archive:
    folder: str
    records: DataFrame
    directory: DataFrame


def _roles(pages: DataFrame, min_bytes: int) -> DataFrame:
    """page_id, digest and the page that it revisits (null for responses)."""
    own = stored(pages.select("page_id", "digest", F.octet_length("html").alias("bytes")), "warc-digests")
    largest = own.where(F.col("bytes") >= min_bytes).groupBy("digest").agg(F.max("page_id").alias("first"))
    role = own.join(largest, "digest", "left").select("page_id", "digest", F.when(F.col("first") != F.col("page_id"), F.col("first")).alias("refers_to"))
    return role.dropDuplicates(["page_id", "digest"])


def write_archive(pages: DataFrame, min_bytes: int = 0, level: int = 6, file_bytes: int = FILE_BYTES, block_lines: int = BLOCK_LINES) -> Archive:
    """Writes all records and the index; pages need page_id, url and html."""
    folder = scratch(pages.sparkSession, "warc")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html")).withColumn("digest", F.sha2("html", 256))
    role = _roles(rows, min_bytes)
    joined = rows.join(role.withColumnRenamed("page_id", "_page"), F.col("page_id").eqNullSafe(F.col("_page")) & (rows["digest"] == role["digest"])).select("page_id", "url", "html", "refers_to")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = file_system(folder)
        fs.create_dir(root, recursive=True)
        part, out, at, name = TaskContext.get().partitionId(), None, 0, ""
        try:
            for batch in batches:
                cols: dict = {c: [] for c in ("page_id", "url", "key", "file", "offset", "length")}
                for page, url, html, to in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html", "refers_to")), strict=True):
                    if out is None or at > file_bytes:
                        if out is not None:
                            out.close()
                        name, at = f"part-{part:06d}-{uuid.uuid4().hex[:10]}.warc.gz", 0
                        out = fs.open_output_stream(f"{root}/{name}", compression=None)
                    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
                    data = packer.compress(record_bytes(page, url, html.encode("utf-8", "surrogatepass"), to)) + packer.flush()
                    out.write(data)
                    for c, v in zip(cols, (page, url, url_key(url), name, at, len(data)), strict=True):
                        cols[c].append(v)
                    at += len(data)
                yield pa.RecordBatch.from_pydict(cols, schema=pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("key", pa.string()), ("file", pa.string()), ("offset", pa.int64()), ("length", pa.int64())]))
        finally:
            if out is not None:
                out.close()

    records = stored(joined.mapInArrow(run, _RECORD), "warc-records")
    return Archive(folder, records, write_index(records, folder, block_lines))


def write_index(records: DataFrame, folder: str, block_lines: int = BLOCK_LINES) -> DataFrame:
    """Packs the sorted lines into blocks; returns the directory (first_key, last_key, file, offset, length, lines)."""
    ordered = records.repartitionByRange("key", "page_id").sortWithinPartitions("key", "page_id", "file", "offset")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = file_system(folder)
        fs.create_dir(root, recursive=True)
        name, at, lines, rows, out = f"index-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex[:10]}.cdx.gz", 0, [], [], None

        def pack():
            nonlocal at, lines, out
            if out is None:
                out = fs.open_output_stream(f"{root}/{name}", compression=None)
            data = gzip.compress("".join(f"{k} {v}\n" for k, v in lines).encode("utf-8", "surrogatepass"), 6, mtime=0)
            out.write(data)
            rows.append((lines[0][0], lines[-1][0], name, at, len(data), len(lines)))
            at, lines = at + len(data), []

        for batch in batches:
            for row in batch.to_pylist():
                lines.append((row["key"], json.dumps({"id": row["page_id"], "url": row["url"], "file": row["file"], "offset": row["offset"], "length": row["length"]})))
                if len(lines) == block_lines:
                    pack()
        if lines:
            pack()
        if out is not None:
            out.close()
        names = ("first_key", "last_key", "file", "offset", "length", "lines")
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64()))], names=list(names))

    return stored(ordered.mapInArrow(run, "first_key string, last_key string, file string, offset long, length long, lines long"), "warc-directory")


def _range(fs, path: str, offset: int, length: int) -> bytes:
    with fs.open_input_file(path) as f:
        return f.read_at(length, offset)


def _block(fs, root: str, file: str, offset: int, length: int) -> list[tuple[str, dict]]:
    text = gzip.decompress(_range(fs, f"{root}/{file}", offset, length)).decode("utf-8", "surrogatepass")
    return [(k, json.loads(v)) for k, _, v in (line.partition(" ") for line in text.split("\n")[:-1])]


class Directory:
    """The sparse directory of an archive, opened for look-ups: its parts' key ranges, and parts as they are asked for."""

    def __init__(self, archive: Archive):
        self.folder, self.table = archive.folder, archive.directory
        ranges = archive.directory.groupBy("file").agg(F.min("first_key").alias("first"), F.max("last_key").alias("last"))
        self.parts = sorted((r["first"], r["last"], r["file"]) for r in ranges.toLocalIterator())
        self.blocks: dict[str, list] = {}

    def part(self, file: str) -> list[tuple]:
        """A part's blocks (first key, last key, file, offset, length), in order."""
        if file not in self.blocks:
            rows = self.table.where(F.col("file") == file).select("first_key", "last_key", "file", "offset", "length").collect()
            self.blocks[file] = sorted(map(tuple, rows), key=lambda b: b[3])
        return self.blocks[file]

    @staticmethod
    def around(ranges: list, key: str) -> Iterator[tuple]:
        """The ranges, sorted and at most touching, that may hold a key: bisected by their last keys."""
        for k in range(bisect.bisect_left(ranges, key, key=lambda r: r[1]), len(ranges)):
            if ranges[k][0] > key:
                return
            yield ranges[k]

    def look_up(self, url: str) -> list[dict]:
        """All records of a URL."""
        key = url_key(url)
        fs, root = file_system(self.folder)
        out = []
        for _, _, file in self.around(self.parts, key):
            for _, _, file, offset, length in self.around(self.part(file), key):
                lines = _block(fs, root, file, offset, length)
                at = bisect.bisect_left(lines, key, key=lambda x: x[0])
                while at < len(lines) and lines[at][0] == key:
                    line = lines[at][1]
                    out.append(line | parse_record(gzip.decompress(_range(fs, f"{root}/{line['file']}", line["offset"], line["length"]))))
                    at += 1
        return out


def look_up(archive: Archive, url: str) -> list[dict]:
    """All records of a URL, by a directory opened for this one."""
    return Directory(archive).look_up(url)


def read_archive(archive: Archive) -> DataFrame:
    """Every record of the archive, found through the index and read by byte range."""
    folder, spark = archive.folder, archive.records.sparkSession
    tasks = max(2, spark.sparkContext.defaultParallelism)

    def lines(batch: pa.RecordBatch) -> dict:
        fs, root = file_system(folder)
        got = [v for r in batch.to_pylist() for _, v in _block(fs, root, r["file"], r["offset"], r["length"])]
        return {c: [g[c] for g in got] for c in ("id", "file", "offset", "length")}

    found = mapped(archive.directory.repartition(tasks, "file", "offset"), lines, "id long, file string, offset long, length long")
    found = found.repartition("file", F.floor(F.col("offset") / F.lit(16 << 20))).sortWithinPartitions("file", "offset")

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = file_system(folder)
        name, f = None, None
        for batch in batches:
            out: dict = {c: [] for c in ("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")}
            for file, offset, length in zip(*(batch.column(c).to_pylist() for c in ("file", "offset", "length")), strict=True):
                if file != name:
                    if f is not None:
                        f.close()
                    name, f = file, fs.open_input_file(f"{root}/{file}")
                got = parse_record(zlib.decompress(f.read_at(length, offset), 31))
                h, to = got["fields"], got["fields"].get("WARC-Refers-To")
                told = h["WARC-Payload-Digest"].removeprefix("sha1:")
                if h["WARC-Type"] == "response" and payload_digest(got["payload"]) != told:
                    raise ValueError(f"digest of {h['WARC-Record-ID']} does not match its payload")
                for c, v in zip(out, (_page(h["WARC-Record-ID"]), len(got["payload"]), told, h["WARC-Type"], _page(to)), strict=True):
                    out[c].append(v)
            yield pa.RecordBatch.from_arrays([pa.array(out["page_id"], pa.int64()), pa.array(out["payload_bytes"], pa.int64()), pa.array(out["payload_digest"], pa.string()), pa.array(out["record_type"], pa.string()), pa.array(out["refers_to"], pa.int64())], names=list(out))
        if f is not None:
            f.close()

    return found.mapInArrow(fetch, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def round_trip(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Writes the archive, reads it back, and gives revisits the size of the payload that they refer to."""
    read = stored(read_archive(write_archive(pages, min_bytes)), "warc-read")
    full = read.where("record_type = 'response'").select(F.col("page_id").alias("refers_to"), F.col("payload_digest"), F.col("payload_bytes").alias("full")).dropDuplicates(["refers_to", "payload_digest"])
    revisits = read.where("record_type = 'revisit'").join(full, ["refers_to", "payload_digest"]).select("page_id", F.col("full").alias("payload_bytes"), "payload_digest", "record_type", "refers_to")
    return read.where("record_type = 'response'").unionByName(revisits)
