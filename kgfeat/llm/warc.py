"""WARC archives: one gzip member per record, written and read as streams.

Writer: each partition streams its records into one file of the archive folder, under a name of its
own attempt, and renames it at the end, so a task that is lost or repeated leaves no half file behind
the names in the manifest. Reader: each file is a task that inflates it chunk by chunk, frames
records by Content-Length and checks both digests while it reads; it holds a chunk, not a file.

Pages with equal payloads of ``least`` bytes or more are stored once: the page with the largest id is
the response, the others are revisit records that refer to it.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, types as T
from pyspark.sql import functions as F

from kgfeat.plans.state import Workspace

LEAST = 1000
CHUNK = 1 << 16
DATE = "2000-01-01T00:00:00Z"  # the table has no times; a fixed one keeps archives alike in every run
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _open(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path if "://" in path else "file://" + path.removeprefix("file:"))


def record_id(page_id: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}')}>"


def _b32(hexed: str) -> str:
    return "sha1:" + base64.b32encode(bytes.fromhex(hexed)).decode()


def record(page_id: object, url: str | None, payload: bytes, digest: str, refers_to: object | None) -> bytes:
    """One WARC record as a gzip member of its own."""
    revisit = refers_to is not None
    block = HTTP if revisit else HTTP + payload
    head = [
        ("WARC-Type", "revisit" if revisit else "response"),
        ("WARC-Record-ID", record_id(page_id)),
        ("WARC-Date", DATE),
        ("WARC-Target-URI", (url or "").replace("\r", "%0D").replace("\n", "%0A")),
        ("WARC-Page-ID", "" if page_id is None else str(page_id)),
        ("WARC-Payload-Digest", _b32(digest)),
        ("WARC-Payload-Length", str(len(payload))),
        ("WARC-Block-Digest", _b32(hashlib.sha1(block).hexdigest())),
        ("Content-Type", "application/http; msgtype=response"),
    ]
    if revisit:
        head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to)), ("WARC-Refers-To-Page-ID", str(refers_to))]
    text = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head) + f"Content-Length: {len(block)}\r\n\r\n"
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(text.encode("utf-8", "surrogatepass") + block + b"\r\n\r\n") + z.flush()


def plan_records(ws: Workspace, pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", least: int = LEAST) -> DataFrame:
    """(i, u, h, d, r): id, url, payload, digest, and the id of the response that a revisit refers to.
    Rows that share the largest id are all responses. Other columns of pages are not archived."""
    page = pages.select(F.col(id_col).alias("i"), F.col(url_col).alias("u"), F.col(payload_col).alias("h"))
    page = page.withColumn("d", F.sha1(F.encode(F.coalesce("h", F.lit("")), "UTF-8")))
    long = page.filter(F.octet_length("h") >= least)
    first = ws.save(long.groupBy("d").agg(F.count("*").alias("n"), F.max("i").alias("first")).filter("n > 1").drop("n"), "shared")
    return page.join(first, "d", "left").select("i", "u", "h", "d", F.when(~F.col("i").eqNullSafe(F.col("first")), F.col("first")).alias("r"))


def write_archives(ws: Workspace, planned: DataFrame, folder: str) -> DataFrame:
    """Write ``planned`` (see plan_records); the manifest (path, records, bytes) of the files that count."""
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ctx = TaskContext.get()
        system, at = _open(folder)
        system.create_dir(at, recursive=True)
        name = f"{at}/part-{ctx.partitionId():05d}-{ctx.taskAttemptId()}.warc.gz"
        n = size = 0
        with system.open_output_stream(name + ".open", compression=None) as out:
            for b in batches:
                for i, u, h, d, r in zip(*b.columns, strict=True):
                    payload = (h.as_py() or "").encode("utf-8", "surrogatepass")
                    data = record(i.as_py(), u.as_py(), payload, d.as_py(), r.as_py())
                    out.write(data)
                    n, size = n + 1, size + len(data)
        if n:
            system.move(name + ".open", name)
        else:
            system.delete_file(name + ".open")
        yield pa.RecordBatch.from_pydict({"file": [name.rsplit("/", 1)[1]] if n else [], "records": [n] if n else [], "bytes": [size] if n else []}, schema=pa.schema([("file", pa.string()), ("records", pa.int64()), ("bytes", pa.int64())]))

    made = ws.save(planned.mapInArrow(write, "file string, records long, bytes long"), "manifest")
    return made.withColumn("path", F.concat(F.lit(folder + "/"), "file"))


class Inflater:
    """Pulls bytes of one gzip member after the other out of a stream, a chunk at a time."""

    def __init__(self, stream, chunk: int = CHUNK):
        self.stream, self.chunk, self.left = stream, chunk, b""

    def members(self) -> Iterator[Iterator[bytes]]:
        while self.left or self._more():
            yield self._member()

    def _more(self) -> bool:
        self.left = self.stream.read(self.chunk)
        return bool(self.left)

    def _member(self) -> Iterator[bytes]:
        z = zlib.decompressobj(31)
        while not z.eof:
            if not self.left and not z.unconsumed_tail and not self._more():
                raise EOFError("the archive ends within a record")
            data, self.left = z.unconsumed_tail + self.left, b""
            out = z.decompress(data, self.chunk)  # at most a chunk, however well it is packed
            if z.eof:
                self.left = z.unused_data
            if out:
                yield out


class Bytes:
    """Exact reads from an iterator of byte strings."""

    def __init__(self, parts: Iterator[bytes]):
        self.parts, self.buf = parts, bytearray()

    def until(self, mark: bytes) -> bytes:
        """All up to mark, however far; the end of the member without one is an error."""
        seen = 0
        while (k := self.buf.find(mark, max(0, seen - len(mark)))) < 0:
            seen = len(self.buf)
            self.buf += next(self.parts, b"") or self._short()
        out = bytes(self.buf[:k])
        del self.buf[: k + len(mark)]
        return out

    def exactly(self, n: int) -> Iterator[bytes]:
        while n:
            if not self.buf:
                self.buf += next(self.parts, b"") or self._short()
            piece = bytes(self.buf[:n])
            del self.buf[: len(piece)]
            n -= len(piece)
            yield piece

    @staticmethod
    def _short() -> bytes:
        raise EOFError("the record is shorter than its Content-Length")


def read_stream(stream, payloads: bool = False, chunk: int = CHUNK) -> Iterator[dict]:
    """Records of one archive in order: headers, payload length and digest, ``ok``, the payload if asked."""
    for member in Inflater(stream, chunk).members():
        src = Bytes(member)
        lines = src.until(b"\r\n\r\n").decode("utf-8", "surrogatepass").split("\r\n")
        head = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        block, body, seen, kept, opening = hashlib.sha1(), hashlib.sha1(), 0, [], bytearray()
        inside = False
        for piece in src.exactly(int(head["content-length"])):
            block.update(piece)
            if not inside:
                opening += piece
                k = opening.find(b"\r\n\r\n")
                if k < 0:
                    continue
                inside, piece = True, bytes(opening[k + 4 :])
            body.update(piece)
            seen += len(piece)
            if payloads:
                kept.append(piece)
        framed = b"".join(src.exactly(4)) == b"\r\n\r\n" and not src.buf and next(src.parts, None) is None
        revisit = head["warc-type"] == "revisit"
        hexed = base64.b32decode(head["warc-payload-digest"].removeprefix("sha1:")).hex()
        ok = framed and lines[0].startswith("WARC/1.") and _b32(block.hexdigest()) == head["warc-block-digest"] and (revisit or body.hexdigest() == hexed)
        yield {"head": head, "type": head["warc-type"], "bytes": int(head["warc-payload-length"]) if revisit else seen, "digest": hexed if revisit else body.hexdigest(), "ok": ok, "payload": b"".join(kept)}


def read_archives(manifest: DataFrame, id_type: T.DataType | None = None) -> DataFrame:
    """(page_id, url, payload_bytes, payload_digest, record_type, refers_to, ok), read from the files.

    A record whose framing or digests are wrong has ok = false; a file that ends early raises an error.
    """
    kind = id_type or T.LongType()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_type

        at = to_arrow_type(kind)
        value = (lambda x: None if x is None or x == "" else int(x)) if pa.types.is_integer(at) else (lambda x: x)
        shape = pa.schema([("page_id", at), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", at), ("ok", pa.bool_())])
        for b in batches:
            for path in b.column(0):
                system, name = _open(path.as_py())
                rows: list[tuple] = []
                with system.open_input_stream(name, compression=None) as stream:
                    for r in read_stream(stream):
                        h = r["head"]
                        rows.append((value(h["warc-page-id"]), h["warc-target-uri"], r["bytes"], r["digest"], r["type"], value(h.get("warc-refers-to-page-id")), r["ok"]))
                        if len(rows) >= 4096:
                            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), shape, strict=True)], schema=shape)
                            rows = []
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), shape, strict=True)], schema=shape)

    k = kind.simpleString()
    return manifest.select("path").mapInArrow(run, f"page_id {k}, url string, payload_bytes long, payload_digest string, record_type string, refers_to {k}, ok boolean")


def round_trip(spark: SparkSession, pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", least: int = LEAST, folder: str | None = None, ws: Workspace | None = None) -> DataFrame:
    """Write every page, read the archives back; fails if a record is not what was written.

    Null payloads are empty, null urls empty and urls and payloads of any length whole; rows with equal
    ids each have their record, a null id stays null. Other columns of pages play no part. No pages: no
    files and an empty result.
    """
    ws = ws or Workspace(spark, "warc")
    made = write_archives(ws, plan_records(ws, pages, id_col, url_col, payload_col, least), folder or ws.path("archives"))
    n = made.count()
    read = read_archives(made.repartition(max(1, n)), pages.schema[id_col].dataType)
    # tied to a column that every use of a record keeps, so that leaving out ok does not leave out the check
    damaged = F.raise_error(F.concat(F.lit("damaged record of page "), F.coalesce(F.col("page_id").cast("string"), F.lit("null"))))
    checked = {c: F.when(F.col("ok"), F.col(c)).otherwise(damaged.cast(read.schema[c].dataType)) for c in read.columns if c != "ok"}
    return read.withColumns(checked)
