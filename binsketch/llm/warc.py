"""WARC archives: writing, reading back, and assembling captures.

A capture is three records: the request, the response (or the revisit of an
earlier response with the same payload) and metadata, which both of the others
name through WARC-Concurrent-To. The page's id is in the metadata record only,
so that a reader has to assemble captures to know it.
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
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh_path, tidy, written

FILE_BYTES, LEVEL, STEP, MOST_READERS = 24_000_000, 1, 1 << 16, 20_000
#: The profile of a revisit, and the date all records bear (the tables have none).
SAME_PAYLOAD, DATE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "2024-01-01T00:00:00Z"
HTTP_OK = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page: int | None, url: str, payload_hex: str, kind: str, copy: int = 0) -> str:
    """The same for the same page (and the same copy of a repeated row), so that a retried task writes the same bytes."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{kind}|{page}|{payload_hex}|{url}' + (f'|{copy}' if copy else ''))}>"


def record(kind: str, own: str, block: bytes, fields: dict[str, str]) -> bytes:
    """One record as a gzip member."""
    head = {"WARC-Type": kind, "WARC-Record-ID": own, "WARC-Date": DATE, **fields, "Content-Length": str(len(block))}
    raw = b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()).encode() + b"\r\n" + block + b"\r\n\r\n"
    gz = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return gz.compress(raw) + gz.flush()


def one_line(url: str | None) -> str:
    return "".join(c if c > " " else f"%{ord(c):02X}" for c in url or "")


def capture(page: int | None, url: str, payload: bytes, payload_hex: str, first: tuple[int | None, str] | None, copy: int = 0) -> bytes:
    """The three records of a page; ``first`` is the page (id, url) whose payload it repeats."""
    kind = "revisit" if first else "response"
    own, ask, note = (record_id(page, url, payload_hex, k, copy) for k in (kind, "request", "metadata"))
    named = {"WARC-Target-URI": url} if url else {}
    main = named | {"WARC-Payload-Digest": f"sha1:{digest(payload)}", "Content-Type": "application/http;msgtype=response"}
    if first:
        main |= {"WARC-Profile": SAME_PAYLOAD, "WARC-Refers-To": record_id(*first, payload_hex, "response")}
    parts = urlsplit(url) if "://" in url else None
    get = f"GET {(parts.path or '/') if parts else '/'} HTTP/1.1\r\nHost: {parts.netloc if parts else ''}\r\n\r\n".encode()
    return (
        record("request", ask, get, named | {"WARC-Concurrent-To": own, "Content-Type": "application/http;msgtype=request"})
        + record(kind, own, HTTP_OK + (b"" if first else payload), main)
        + record("metadata", note, b"" if page is None else f"page: {page}\r\n".encode(), named | {"WARC-Concurrent-To": own, "Content-Type": "application/warc-fields"})
    )


def place(folder: str):
    """The store and the folder's path in it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder)


def put(folder: str, name: str, blob: bytes) -> None:
    """A file appears whole or not at all: written beside its place, then moved."""
    store, root = place(folder)
    store.create_dir(root, recursive=True)
    aside = f"{root}/.{name}-{uuid.uuid4().hex}"
    with store.open_output_stream(aside) as f:
        f.write(blob)
    store.move(aside, f"{root}/{name}")


def write_warc(pages: DataFrame, folder: str, file_bytes: int = FILE_BYTES) -> DataFrame:
    """Archives of all pages in ``folder``; returns one row per archive (name, pages, bytes) of the finished job.

    ``pages`` has page_id, url, html. Null html counts as empty; a page without a
    page_id is archived without one; each of several equal rows has a capture of its
    own. Of equal payloads the largest page_id (then url, then the first copy) is the
    response and the others revisit it. Payloads meet by their digest in rows without
    html, and a hot one is a skewed join that Spark splits; html is dealt out by page,
    equal rows once a task. A name bears its task's attempt, and only names of
    attempts that Spark's committer took are returned: what a lost or doubled attempt
    leaves in the folder is never read. An empty table writes nothing.
    """
    key = ["page", "none", "url", "hex"]  # without nulls, so that the join keeps the way that html is dealt out
    body = F.coalesce(F.col("html"), F.lit(""))
    rows = pages.select(F.coalesce(F.col("page_id"), F.lit(0)).cast("long").alias("page"), F.isnull("page_id").alias("none"), F.coalesce(F.col("url"), F.lit("")).alias("url"), F.sha1(body.cast("binary")).alias("hex"), body.alias("html"))
    slim = rows.groupBy(*key).agg(F.count(F.lit(1)).alias("n"))
    own = F.struct(F.when(~F.col("none"), F.col("page")).alias("page_id"), "url")
    first = slim.groupBy("hex").agg(F.max(own).alias("first"), F.sum("n").alias("all")).filter("`all` > 1").select(F.col("hex").alias("of"), "first")
    facts = slim.join(first, F.col("hex") == F.col("of"), "left").select(*key, "n", "first")
    whole = rows.groupBy(*key).agg(F.first("html").alias("html"))
    kind = "name string, pages long, bytes long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, attempt, seq, held, pages_in, size = TaskContext.get().partitionId(), TaskContext.get().taskAttemptId(), 0, [], 0, 0
        done = []

        def close():
            nonlocal seq, held, pages_in, size
            name = f"part-{part:06d}-{attempt}-{seq:04d}.warc.gz"
            put(folder, name, b"".join(held))
            done.append((name, pages_in, size))
            seq, held, pages_in, size = seq + 1, [], 0, 0

        for batch in batches:
            for r in batch.to_pylist():
                best = r["first"] and (r["first"]["page_id"], one_line(r["first"]["url"]))
                page, url, payload = None if r["none"] else r["page"], one_line(r["url"]), r["html"].encode()
                for copy in range(r["n"]):
                    held.append(capture(page, url, payload, r["hex"], None if not best or best == (page, url) and not copy else best, copy))
                    pages_in, size = pages_in + 1, size + len(held[-1])
                    if size >= file_bytes:
                        close()
        if held:
            close()
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*done, strict=True) if done else ([], [], []), (pa.string(), pa.int64(), pa.int64()), strict=True)], names=["name", "pages", "bytes"])

    return written(whole.join(facts, key).select(*key, "html", "n", "first").mapInArrow(tidy(run), kind), "warc-names")


def members(archive) -> Iterator[bytes]:
    """The gzip members of an archive (bytes, or a file to read on), one after the other; a member at a time is held."""
    source = io.BytesIO(archive) if isinstance(archive, bytes) else archive
    chunk = source.read(STEP)
    while chunk:
        gz, parts = zlib.decompressobj(31), []
        while not gz.eof:
            if not chunk:
                raise ValueError("an archive that ends within a record")
            parts.append(gz.decompress(chunk))
            chunk = gz.unused_data if gz.eof else source.read(STEP)
        yield b"".join(parts)
        chunk = chunk or source.read(STEP)


def parsed(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields (lower-case names) and block of a record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    return fields, rest[: int(fields["content-length"])]


def read_warc(archives: DataFrame, with_payload: bool = False, folder: str | None = None) -> DataFrame:
    """One row per record: record_id, record_type, concurrent_to, refers_to, url, payload_bytes, payload_digest
    (of the block's own bytes; of the header for a revisit), page_id (of metadata), payload if asked for.

    ``archives`` are binaryFile rows (content), or names of files in ``folder``, which
    are read on record by record."""
    kind = "record_id string, record_type string, concurrent_to string, refers_to string, url string, payload_bytes long, payload_digest string, page_id long" + ", payload binary" * with_payload
    names = [x.split()[0] for x in kind.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in batch.column(0).to_pylist():
                rows: list[tuple] = []
                for raw in members(at if folder is None else opened(folder, at)):
                    fields, block = parsed(raw)
                    what, payload, page = fields["warc-type"], None, None
                    said = fields.get("warc-payload-digest", "").rpartition(":")[2] or None
                    if what == "response":
                        payload = block.partition(b"\r\n\r\n")[2]
                        if digest(payload) != said:
                            raise ValueError(f"record {fields['warc-record-id']}: its payload has another digest")
                    elif what == "metadata":
                        page = next((int(x[5:]) for x in block.decode().split("\r\n") if x.startswith("page:")), None)
                    rows.append((fields["warc-record-id"], what, fields.get("warc-concurrent-to"), fields.get("warc-refers-to"), fields.get("warc-target-uri"), None if payload is None else len(payload), said, page, payload)[: len(names)])
                    if len(rows) >= 2048:
                        yield _rows(rows, names)
                        rows = []
                if rows:
                    yield _rows(rows, names)

    return archives.select("content" if folder is None else "name").mapInArrow(tidy(run), kind)


def opened(folder: str, name: str):
    store, root = place(folder)
    return store.open_input_stream(f"{root}/{name}", compression=None)  # members are told apart here


def _rows(rows: list[tuple], names: list[str]) -> pa.RecordBatch:
    kinds = {"payload_bytes": pa.int64(), "page_id": pa.int64(), "payload": pa.binary()}
    return pa.RecordBatch.from_arrays([pa.array(c, kinds.get(n, pa.string())) for n, c in zip(names, zip(*rows, strict=True), strict=True)], names=names)


def captures(records: DataFrame) -> DataFrame:
    """One nested row per capture: capture_id, page_id, response, request, metadata (structs; null where a record is missing).

    ``response`` is the response or revisit record. Records meet through the id
    that they are concurrent to; equal records read twice count once.
    """
    fields = [c for c in records.columns if c != "concurrent_to"]
    kind = F.col("record_type")
    of = lambda *kinds: F.max(F.when(kind.isin(*kinds), F.struct(*fields)))
    grouped = records.groupBy(F.coalesce("concurrent_to", "record_id").alias("capture_id")).agg(of("response", "revisit").alias("response"), of("request").alias("request"), of("metadata").alias("metadata"))
    return grouped.select("capture_id", F.col("metadata.page_id").alias("page_id"), "response", "request", "metadata")


def archive_digests(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """Write, read back and assemble: page_id, payload_bytes, payload_digest, record_type, refers_to (the response's page_id).

    One row per row of ``pages``. Pages without a page_id have a null one; of equal
    rows one may be the response, and the others revisit it.
    """
    spark = pages.sparkSession
    folder = folder or fresh_path(spark, "warc")
    names = write_warc(pages, folder)
    n = names.count()
    if not n:
        return spark.createDataFrame([], "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")
    spread = names.repartition(min(n, MOST_READERS), F.monotonically_increasing_id())
    found = written(captures(read_warc(spread, folder=folder)).select("page_id", F.col("response.record_id").alias("record_id"), "response.record_type", "response.payload_bytes", "response.payload_digest", F.col("response.refers_to").alias("to")), "captures")
    response, revisit = found.filter("record_type = 'response'"), found.filter("record_type = 'revisit'")
    target = response.select(F.col("record_id").alias("to"), F.col("page_id").alias("to_page"), F.col("payload_bytes").alias("to_bytes"))
    own = response.select("page_id", "payload_bytes", "payload_digest", "record_type", F.lit(None).cast("long").alias("refers_to"))
    return own.unionByName(revisit.join(target, "to", "left").select("page_id", F.col("to_bytes").alias("payload_bytes"), "payload_digest", "record_type", F.col("to_page").alias("refers_to")))
