"""Web archives: writing captures as WARC records, reading them back, and assembling transactions.

A capture is a request, a response (or a revisit of one with the same payload) and a metadata record; the first and the
last name the second in WARC-Concurrent-To.  Archives hold one gzip member per record and lie in a folder that all
executors reach by its file system's own interface.
"""

from __future__ import annotations

import base64
import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shared_folder, slices, text_or_empty, texts, written

DATE = "2024-01-01T00:00:00Z"
LEAST_REVISIT = 1000
FILE_BYTES = 512 << 20
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def record_id(kind: str, key: str) -> str:
    return f"<urn:uuid:{uuid.UUID(bytes=hashlib.sha1(f'{kind}|{key}'.encode()).digest()[:16])}>"


def member(headers: list[tuple[str, str]], block: bytes) -> bytes:
    """One record as a gzip member."""
    head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in headers) + f"Content-Length: {len(block)}\r\n\r\n"
    z = zlib.compressobj(1, zlib.DEFLATED, 31)
    return z.compress(head.encode() + block + b"\r\n\r\n") + z.flush()


def one_line(text: str) -> str:
    return " ".join(text.split())


def capture(key: str, page: int | None, url: str, payload: bytes, target: tuple[str, int | None] | None, date: str) -> bytes:
    """The three records of a capture; ``target`` is (key, page) of the response that a revisit stands for."""
    sha = hashlib.sha1(payload).digest()
    me, url = record_id("response", key), one_line(url)
    parts = urlsplit(url) if "[" not in url else None
    about = [("WARC-Target-URI", url or "about:blank"), ("WARC-Date", date)]
    digest = ("WARC-Payload-Digest", f"sha1:{base64.b32encode(sha).decode()}")
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    path = (parts.path or "/") if parts else "/"
    get = f"GET {path} HTTP/1.1\r\nHost: {parts.netloc if parts else ''}\r\n\r\n".encode()
    note = f"page-id: {'' if page is None else page}\r\n".encode()
    out = [member([("WARC-Type", "request"), ("WARC-Record-ID", record_id("request", key)), ("WARC-Concurrent-To", me), *about, ("Content-Type", "application/http; msgtype=request")], get)]
    kind = ("Content-Type", "application/http; msgtype=response")
    if target is None:
        out.append(member([("WARC-Type", "response"), ("WARC-Record-ID", me), *about, digest, kind], http + payload))
    else:
        refers = ("WARC-Refers-To", record_id("response", target[0]))
        out.append(member([("WARC-Type", "revisit"), ("WARC-Record-ID", me), *about, digest, ("WARC-Profile", REVISIT_PROFILE), refers, kind], http))
    out.append(member([("WARC-Type", "metadata"), ("WARC-Record-ID", record_id("metadata", key)), ("WARC-Concurrent-To", me), *about, ("Content-Type", "application/warc-fields")], note))
    return b"".join(out)


def write_archives(pages: DataFrame, folder: str, date: str = DATE, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least: int = LEAST_REVISIT) -> DataFrame:
    """Writes every row of ``pages`` as a capture and returns the manifest (path, captures, bytes).

    Of rows with equal payloads of at least ``least`` bytes the one with the largest id (then the last row) holds the
    response, the others revisit it.  A null payload is empty; a null id or url stays null or blank.  A file is moved to
    its name when it is complete, so a repeated task replaces its own files.
    """
    row = F.monotonically_increasing_id().alias("row")
    html = text_or_empty(html_col)
    rows = pages.select(row, F.col(id_col).cast("long").alias("page"), text_or_empty(url_col).alias("url"), html.alias("html"))
    marks = written(rows.select("row", "page", F.octet_length("html").alias("n"), F.sha2("html", 256).alias("sha")).filter(F.col("n") >= least), "payloads")
    chosen = marks.groupBy("sha", "n").agg(F.max(F.struct("page", "row")).alias("to"), F.count(F.lit(1)).alias("k")).filter("k > 1")
    revisits = marks.join(chosen, ["sha", "n"]).filter(F.col("row") != F.col("to.row")).select("row", F.col("to.page").alias("to_page"), F.col("to.row").alias("to_row"))
    planned = rows.join(revisits, "row", "left").select("row", "page", "url", "html", "to_page", "to_row")

    def run(batches):
        fs, base = pafs.FileSystem.from_uri(folder)
        fs.create_dir(base, recursive=True)
        task, number, out, size, held = TaskContext.get(), 0, None, 0, 0
        name, temp = "", ""

        def close():
            out.close()
            fs.move(temp, name)
            return name, held, size

        done = []
        for b in slices(batches, "html"):
            for r, page, url, html, to_page, to_row in zip(*(b.column(c).to_pylist() for c in ("row", "page", "url", "html", "to_page", "to_row"))):
                if out is None:
                    name = f"{base}/part-{task.partitionId():06d}-{number:04d}.warc.gz"
                    temp = f"{name}.{task.taskAttemptId()}"
                    out, size, held, number = fs.open_output_stream(temp, compression=None), 0, 0, number + 1
                data = capture(str(r), page, url, html.encode("utf-8", "replace"), None if to_row is None else (str(to_row), to_page), date)
                out.write(data)
                size, held = size + len(data), held + 1
                if size >= FILE_BYTES:
                    done.append(close())
                    out = None
        if out is not None:
            done.append(close())
        if done:
            n, h, s = zip(*done)
            yield pa.RecordBatch.from_arrays([pa.array(n), pa.array(h, pa.int64()), pa.array(s, pa.int64())], names=["path", "captures", "bytes"])

    return written(texts(planned).mapInArrow(run, "path string, captures long, bytes long"), "manifest")


def members(stream, block: int = 1 << 20) -> Iterator[bytes]:
    """The gzip members of a file, one at a time."""
    z, out, data = zlib.decompressobj(31), io.BytesIO(), stream.read(block)
    while data:
        out.write(z.decompress(data))
        if z.eof:
            yield out.getvalue()
            data = z.unused_data or stream.read(block)
            z, out = zlib.decompressobj(31), io.BytesIO()
        else:
            data = stream.read(block)
    if out.tell():
        raise ValueError("the archive ends within a record")


def parse(record: bytes) -> tuple[dict[str, str], bytes]:
    head, _, rest = record.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError(f"not a WARC record: {lines[0][:40]}")
    headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    return headers, rest[: int(headers.get("content-length", 0))]


def read_archives(manifest: DataFrame, folder: str, keep_payload: bool = True) -> DataFrame:
    """One row per record of the files of a manifest; the payload's size and SHA-1 are those of what was read.

    A revisit has the size and digest that its headers state, since it holds no payload.
    """
    fields = ["id", "type", "concurrent_to", "refers_to", "uri", "date", "payload_bytes", "payload_digest", "body", "payload"]

    def run(batches):
        fs, _ = pafs.FileSystem.from_uri(folder)
        for b in batches:
            for path in b.column("path").to_pylist():
                rows, held = [], 0
                with fs.open_input_stream(path, compression=None) as f:
                    for m in members(f):
                        h, block = parse(m)
                        kind, size, sha, body, payload = h.get("warc-type"), None, None, None, None
                        if kind in ("response", "revisit"):
                            head, _, payload = block.partition(b"\r\n\r\n")
                            body = head.decode("utf-8", "replace")
                            if kind == "response":
                                size, sha = len(payload), hashlib.sha1(payload).hexdigest()
                                if base64.b32encode(bytes.fromhex(sha)).decode() != h["warc-payload-digest"].removeprefix("sha1:"):
                                    raise ValueError(f"{h['warc-record-id']}: the payload does not match its digest")
                            else:
                                stated = (x.partition(":") for x in body.split("\r\n"))
                                size = next((int(v) for k, _, v in stated if k.lower() == "content-length"), None)
                                sha, payload = base64.b32decode(h["warc-payload-digest"].removeprefix("sha1:")).hex(), None
                        else:
                            body = block.decode("utf-8", "replace")
                        rows.append((h.get("warc-record-id"), kind, h.get("warc-concurrent-to"), h.get("warc-refers-to"), h.get("warc-target-uri"), h.get("warc-date"), size, sha, body, payload if keep_payload else None))
                        held += len(m)
                        if held > 4 << 20:
                            yield table(rows)
                            rows, held = [], 0
                if rows:
                    yield table(rows)

    def table(rows):
        kinds = [pa.string()] * 6 + [pa.int64(), pa.string(), pa.string(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=fields)

    schema = ", ".join(f"{f} {'long' if f == 'payload_bytes' else 'binary' if f == 'payload' else 'string'}" for f in fields)
    # a task for each file: a count that is given is not coalesced away
    spread = manifest.select("path").repartition(max(1, manifest.count()), F.col("path"))
    return spread.mapInArrow(run, schema)


def transactions(records: DataFrame) -> DataFrame:
    """One nested row per capture: (id, response, request, metadata, page_id, refers_to_page).

    Requests and metadata meet their response or revisit by its id in WARC-Concurrent-To; either may be missing.
    """
    whole = F.struct(*records.columns)
    main = records.filter(F.col("type").isin("response", "revisit")).select("id", whole.alias("response"))
    side = {t: records.filter(F.col("type") == t).select(F.col("concurrent_to").alias("id"), whole.alias(t)).dropDuplicates(["id"]) for t in ("request", "metadata")}
    met = main.join(side["request"], "id", "left").join(side["metadata"], "id", "left")
    page = F.regexp_extract(F.col("metadata.body"), r"page-id: (-?\d+)", 1)
    return met.withColumn("page_id", F.when(page != "", page.cast("long")))


def round_trip(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Per row of ``pages``: id, payload_bytes, payload_digest, record_type, refers_to; written, read and assembled."""
    folder = shared_folder(pages.sparkSession, "warc")
    manifest = write_archives(pages, folder, id_col=id_col, url_col=url_col, html_col=html_col)
    records = written(read_archives(manifest, folder, keep_payload=False), "records")
    captures = transactions(records)
    metadata = records.filter(F.col("type") == "metadata")
    page = F.regexp_extract("body", r"page-id: (-?\d+)", 1)
    of = metadata.select(F.col("concurrent_to").alias("target"), F.when(page != "", page.cast("long")).alias("refers_to"))
    out = captures.select("page_id", F.col("response.payload_bytes").alias("payload_bytes"), F.col("response.payload_digest").alias("payload_digest"), F.col("response.type").alias("record_type"), F.col("response.refers_to").alias("target"))
    return out.join(of, "target", "left").select(F.col("page_id").alias(id_col), "payload_bytes", "payload_digest", "record_type", "refers_to")
