"""WARC archives: write, index first, read back by coalesced byte ranges.

Every record is a gzip member of its own, as the format advises, so a byte range of the archive is a whole record.

Writing: each task appends records to archives of bounded size in the shared folder and emits one index row per record
(archive, offset, length, URL, digest).  The index is a table written once by Spark's committer; archive names are
unique per attempt, so an archive left by a lost or repeated task has no index rows and is never read.

Reading: the index is filtered and sorted by (archive, offset) first; neighbouring ranges are then merged into one read
if the gap between them is small, and records are cut from the merged bytes.

Files are reached through pyarrow's file systems from a URI, so any store pyarrow knows works.

Defined cases: a null html has an empty payload; rows with a null page_id take part with the smallest rank and stay
null; of equal payloads the row with the largest page_id is the response (all rows that share that id are); null URLs
become ``urn:page:<id>``; line breaks and blanks in URLs are percent-encoded.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared

ARCHIVE_BYTES = 64 << 20
GAP_BYTES = 64 << 10
MERGED_BYTES = 8 << 20
INDEX = "page_id long, archive string, offset long, length long, url string, digest string, record_type string, refers_to long"
DATE = "2024-01-01T00:00:00Z"  # fixed, so that repeated runs write equal bytes


def _open(uri: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def clean_url(url: str | None, page_id: int | None) -> str:
    if url is None:
        return f"urn:page:{page_id}"
    return "".join(c if c > " " else f"%{ord(c):02X}" for c in url)


def record(page_id: int | None, url: str, payload: bytes, payload_digest: str, kind: str, refers_to: int | None) -> bytes:
    """One WARC/1.1 record; a revisit repeats no payload but names its length and the response it refers to."""
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}:{kind}')}>", f"WARC-Date: {DATE}", f"WARC-Target-URI: {url}", f"WARC-Payload-Digest: sha1:{payload_digest}", f"X-Page-Id: {'' if page_id is None else page_id}", f"X-Payload-Length: {len(payload)}"]
    body = payload
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{refers_to}:response')}>", f"X-Refers-To-Page: {refers_to}"]
        body = b""
    head += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and body of a record; raises ValueError if it isn't one whole record."""
    head, sep, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not sep or not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
    size = int(fields["Content-Length"])
    if rest[size:] != b"\r\n\r\n":
        raise ValueError("record length is wrong")
    return fields, rest[:size]


def _writer(folder: str, archive_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, root = _open(folder)
        files.create_dir(root, recursive=True)
        out, name, at = None, "", 0
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                if out is None or at >= archive_bytes:
                    if out is not None:
                        out.close()
                    name, at = f"archive-{uuid.uuid4().hex}.warc.gz", 0
                    out = files.open_output_stream(f"{root}/{name}", compression=None)
                payload = (r["html"] or "").encode("utf-8", "replace")
                url, sha = clean_url(r["url"], r["page_id"]), digest(payload)
                raw = gzip.compress(record(r["page_id"], url, payload, sha, r["record_type"], r["refers_to"]), 4, mtime=0)
                out.write(raw)
                rows.append((r["page_id"], name, at, len(raw), url, sha, r["record_type"], r["refers_to"]))
                at += len(raw)
            if rows:
                types = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64()]
                names = ["page_id", "archive", "offset", "length", "url", "digest", "record_type", "refers_to"]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)
        if out is not None:
            out.close()

    return run


def decide(pages: DataFrame) -> DataFrame:
    """page_id, url, html, record_type, refers_to.  Digests without texts find the response of each payload (maxima
    combine before the shuffle); pages then meet only the payloads that occur more than once, in a plain sort-merge join,
    whose hot partitions Spark splits at run time because the other side has one row a payload."""
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    light = pages.select("page_id", F.sha1(payload).alias("sha"), F.length(payload).alias("size"))
    heads = light.groupBy("sha", "size").agg(F.max("page_id").alias("head"), F.count("*").alias("copies")).where("copies > 1").drop("copies")
    own = pages.withColumns({"sha": F.sha1(payload), "size": F.length(payload)})
    joined = own.join(heads, ["sha", "size"], "left")
    revisit = F.col("head").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("head"))
    return joined.select("page_id", "url", "html", F.when(revisit, "revisit").otherwise("response").alias("record_type"), F.when(revisit, F.col("head")).alias("refers_to"))


def write_archives(pages: DataFrame, folder: str | None = None, archive_bytes: int = ARCHIVE_BYTES) -> tuple[str, DataFrame]:
    """Archives in ``folder`` (default: a new one in the shared folder) and their index."""
    folder = folder or shared.scratch(pages.sparkSession)
    index = shared.written(decide(pages).mapInArrow(_writer(folder, archive_bytes), INDEX))
    return folder, index


def merge_ranges(ranges: list[tuple[int, int]], gap: int = GAP_BYTES, most: int = MERGED_BYTES) -> list[tuple[int, int, list[int]]]:
    """(offset, length, members) of merged reads for ranges sorted by offset."""
    out: list[tuple[int, int, list[int]]] = []
    for i, (offset, length) in enumerate(ranges):
        if out and offset - (out[-1][0] + out[-1][1]) <= gap and offset + length - out[-1][0] <= most:
            out[-1] = (out[-1][0], max(out[-1][1], offset + length - out[-1][0]), [*out[-1][2], i])
        else:
            out.append((offset, length, [i]))
    return out


def _reader(folder: str, full: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, root = _open(folder)
        name, handle = None, None
        for batch in batches:
            wanted = batch.to_pylist()
            at = 0
            while at < len(wanted):
                end = at
                while end < len(wanted) and wanted[end]["archive"] == wanted[at]["archive"]:
                    end += 1
                if wanted[at]["archive"] != name:
                    name = wanted[at]["archive"]
                    handle = files.open_input_file(f"{root}/{name}")
                group, at = wanted[at:end], end
                for offset, length, members in merge_ranges([(r["offset"], r["length"]) for r in group]):
                    raw, rows = handle.read_at(length, offset), []
                    for i in members:
                        r = group[i]
                        fields, body = parse(gzip.decompress(raw[r["offset"] - offset : r["offset"] - offset + r["length"]]))
                        sha, kind = fields["WARC-Payload-Digest"].removeprefix("sha1:"), fields["WARC-Type"]
                        if kind == "response" and digest(body) != sha:
                            raise ValueError(f"payload of {fields['WARC-Record-ID']} doesn't match its digest")
                        rows.append((int(fields["X-Page-Id"]) if fields["X-Page-Id"] else None, fields["WARC-Target-URI"], int(fields["X-Payload-Length"]), sha, kind, int(fields["X-Refers-To-Page"]) if kind == "revisit" else None, body.decode() if full else None))
                    types = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()]
                    names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "html"]
                    out = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)]
                    yield pa.RecordBatch.from_arrays(out if full else out[:-1], names=names if full else names[:-1])

    return run


def read_archives(folder: str, index: DataFrame, with_payload: bool = False) -> DataFrame:
    """Records of the index rows (filter the index to select): page_id, url, payload_bytes, payload_digest, record_type,
    refers_to and, if asked for, html (empty for revisits)."""
    schema = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long"
    n = shared.partitions(index.sparkSession)
    # ranges of about equal numbers of records, in file order, so that one large archive spreads over tasks
    wanted = index.select("archive", "offset", "length").repartitionByRange(n, "archive", "offset").sortWithinPartitions("archive", "offset")
    return wanted.mapInArrow(_reader(folder, with_payload), schema + (", html string" if with_payload else ""))


def round_trip(pages: DataFrame) -> DataFrame:
    folder, index = write_archives(pages)
    return read_archives(folder, index).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
