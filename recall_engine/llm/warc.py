"""WARC archives through a chunked record table.

A payload reaches Python as rows (record, chunk number, bytes) of bounded size, never as one value. The writer streams
the chunks of a record into a gzip member of its own; the reader streams them out again, carrying a SHA-256 from chunk
to chunk, and gives the same kind of rows, the last of a record with the finished digest. A payload of any length so
needs memory for one chunk.

Payloads of at least ``min_bytes`` that occur more than once are stored once, in the response with the smallest page_id;
the others become revisit records that name it. Digests of single payloads never leave their task: only those that
occur twice or more join back, and a digest that a third of all pages share is one row after the partial aggregate.

Files are written below the shared folder, one per task, under a name of the task's own, then renamed, so a task that
runs again leaves one whole file.

Defined results: null html is an empty payload; a null page_id is larger than any other and is written without an id;
rows that repeat the smallest page_id of a payload are all responses; page ids may be whole numbers or strings; other
columns, whatever their names, are not read; a payload of any length is one record; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote, unquote

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .scratch import cut, fresh_path, shuffle_partitions

CHUNK_BYTES = 1 << 18
MIN_REVISIT_BYTES = 100
HTTP_HEAD = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _id_column(pages: DataFrame, page_id: str) -> Column:
    return F.col(f"`{page_id}`").cast(id_type(pages.schema[page_id].dataType))


def decided(pages: DataFrame, min_bytes: int = MIN_REVISIT_BYTES, html: str = "html", page_id: str = "page_id", url: str = "url") -> DataFrame:
    """page_id, url, payload, payload_bytes, digest, record_type, refers_to of each row."""
    own = pages.select(_id_column(pages, page_id).alias("page_id"), F.col(f"`{url}`").alias("url"), F.coalesce(F.col(f"`{html}`"), F.lit("")).cast("binary").alias("payload"))
    own = own.withColumn("payload_bytes", F.octet_length("payload").cast("long")).withColumn("digest", F.sha2("payload", 256))
    groups = own.where(F.col("payload_bytes") >= min_bytes).groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n"))
    copies = cut(groups.where("n > 1").select(F.col("digest").alias("_digest"), "first_id"))
    joined = own.join(copies, F.col("digest") == F.col("_digest"), "left")
    revisit = F.col("_digest").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    return joined.select(
        "page_id", "url", F.when(~revisit, F.col("payload")).alias("payload"), "payload_bytes", "digest",
        F.when(revisit, "revisit").otherwise("response").alias("record_type"), F.when(revisit, F.col("first_id")).alias("refers_to"),
    )


def chunks(records: DataFrame, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """The chunked record table: a row per chunk, in order and side by side; records without payload have one empty chunk."""
    body = F.coalesce(F.col("payload"), F.lit(b""))
    last = F.greatest(F.lit(0), F.ceil(F.octet_length(body) / F.lit(float(chunk_bytes))).cast("int") - 1)
    rest = [c for c in records.columns if c != "payload"]
    # Only numbers are generated; each chunk is cut out as its row goes on, so no more than one is there at a time.
    numbered = records.select(*rest, body.alias("payload"), F.explode(F.sequence(F.lit(0), last)).alias("chunk_no"))
    return numbered.select(*rest, "chunk_no", F.substring("payload", F.col("chunk_no") * chunk_bytes + 1, F.lit(chunk_bytes)).alias("chunk"))


def quoted(value: object) -> str:
    """A header value that comes back the same, whatever characters it has."""
    return quote(str(value), safe="")


def _fields(row: dict) -> bytes:
    def clean(value: object) -> str:
        return " ".join(str(value).split())

    head = [
        "WARC/1.1",
        f"WARC-Type: {row['record_type']}",
        f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{row["page_id"]}|{row["url"]}|{row["digest"]}')}>",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha256:{row['digest']}",
        f"X-Payload-Length: {row['payload_bytes']}",
        "Content-Type: application/http;msgtype=response",
    ]
    if row["url"] is not None:
        head.append(f"WARC-Target-URI: {clean(row['url'])}")
    if row["page_id"] is not None:
        head.append(f"X-Page-Id: {quoted(row['page_id'])}")
    if row["record_type"] == "revisit":
        head += [f"WARC-Profile: {REVISIT_PROFILE}", f"X-Refers-To-Page-Id: {quoted(row['refers_to'])}"]
    length = len(HTTP_HEAD) + (row["payload_bytes"] if row["record_type"] == "response" else 0)
    return ("\r\n".join([*head, f"Content-Length: {length}"]) + "\r\n\r\n").encode() + HTTP_HEAD


def write(records: DataFrame, folder: str, level: int = 3) -> list[str]:
    """Writes archives from the chunked record table and returns their names, one per task that had rows."""
    from . import token_files

    names = ("page_id", "url", "payload_bytes", "digest", "record_type", "refers_to")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, path = token_files._open(folder)
        fs.create_dir(path, recursive=True)
        name = f"part-{TaskContext.get().partitionId():06d}.warc.gz"
        temporary, out, member = f"{path}/_{name}-{uuid.uuid4().hex}", None, None
        for b in batches:
            heads, numbers, body = b.select(list(names)), b.column("chunk_no").to_pylist(), b.column("chunk")
            for i, number in enumerate(numbers):
                if number == 0:
                    if out is None:
                        out = fs.open_output_stream(temporary, compression=None)
                    if member is not None:
                        out.write(member.compress(b"\r\n\r\n") + member.flush())
                    member = zlib.compressobj(level, zlib.DEFLATED, 31)
                    out.write(member.compress(_fields({n: heads.column(k)[i].as_py() for k, n in enumerate(names)})))
                out.write(member.compress(body[i].as_py()))
        if out is not None:
            out.write(member.compress(b"\r\n\r\n") + member.flush())
            out.close()
            fs.move(temporary, f"{path}/{name}")
            yield pa.RecordBatch.from_pydict({"file": [name]})

    return sorted(r["file"] for r in records.mapInArrow(run, "file string").collect())  # one row per task


class MemberStream:
    """Plain bytes of a file of gzip members, a bounded piece at a time."""

    def __init__(self, file, piece: int):
        self.file, self.piece, self.rest, self.inflate = file, piece, b"", zlib.decompressobj(31)
        self.ready = bytearray()

    def _more(self) -> bool:
        while True:
            if self.inflate.eof:
                self.rest, self.inflate = self.inflate.unused_data, zlib.decompressobj(31)
            data = self.inflate.unconsumed_tail or self.rest or self.file.read(self.piece)
            self.rest = b""
            if not data:
                return False
            got = self.inflate.decompress(data, self.piece)
            if got:
                self.ready += got
                return True

    def read(self, n: int) -> bytes:
        """Up to ``n`` bytes; fewer only before a piece's end, none at the end of the file."""
        if not self.ready and not self._more():
            return b""
        got = bytes(self.ready[:n])
        del self.ready[:n]
        return got

    def until(self, mark: bytes) -> bytes:
        """Everything before ``mark``, which is passed over; b"" at the end of the file."""
        while (at := self.ready.find(mark)) < 0:
            if not self._more():
                return b""
        got = bytes(self.ready[:at])
        del self.ready[: at + len(mark)]
        return got


def id_type(kind: T.DataType) -> str:
    """The type of ids as files give them back: whole numbers as long, all else as string."""
    return "long" if isinstance(kind, T.IntegralType) else "string"


def read_records(file, chunk_bytes: int = CHUNK_BYTES) -> Iterator[dict]:
    """The chunked record table of an archive: header fields, chunk_no, chunk, and at the last chunk the payload's bytes and digest so far carried."""
    stream = MemberStream(file, chunk_bytes)
    while head := stream.until(b"\r\n\r\n"):
        fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
        left, carried, size, number = int(fields["Content-Length"]), hashlib.sha256(), 0, 0
        http = stream.until(b"\r\n\r\n")
        left -= len(http) + 4
        while True:
            chunk = stream.read(min(left, chunk_bytes)) if left else b""
            if left and not chunk:
                raise ValueError("the archive ends inside a record")
            left -= len(chunk)
            size += len(chunk)
            carried.update(chunk)
            yield {"fields": fields, "chunk_no": number, "chunk": chunk, "last": not left, "size": size, "digest": carried.hexdigest() if not left else None}
            number += 1
            if not left:
                break
        if stream.until(b"\r\n\r\n"):
            raise ValueError("bytes after a record's end")


def read(spark: SparkSession, folder: str, files: list[str], id_type: str = "long") -> DataFrame:
    """A row per record of the archives: page_id, url, payload_bytes, payload_digest, record_type, refers_to.

    A response's bytes and digest come from its payload as read; a revisit's from its header, which names the response's.
    """
    from . import token_files

    schema = f"page_id {id_type}, url string, payload_bytes long, payload_digest string, record_type string, refers_to {id_type}"
    if not files:
        return spark.createDataFrame([], schema)
    names = ("page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to")
    known = {"long": pa.int64(), "int": pa.int32(), "string": pa.string()}[id_type]
    kinds = dict(zip(names, (known, pa.string(), pa.int64(), pa.string(), pa.string(), known), strict=True))
    made = str if id_type == "string" else int

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, path = token_files._open(folder)
        rows: list[tuple] = []

        def batch() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kinds[n]) for k, n in enumerate(names)], names=list(names))

        for b in batches:
            for name in b.column(0).to_pylist():
                with fs.open_input_stream(f"{path}/{name}", compression=None) as f:
                    for c in read_records(f):
                        if c["last"]:
                            h = c["fields"]
                            number = {k: made(unquote(h[k])) if k in h else None for k in ("X-Page-Id", "X-Refers-To-Page-Id")}
                            noted = h["WARC-Payload-Digest"].removeprefix("sha256:")
                            revisit = h["WARC-Type"] == "revisit"
                            if not revisit and (noted != c["digest"] or int(h["X-Payload-Length"]) != c["size"]):
                                raise ValueError("a payload differs from its header")
                            rows.append((number["X-Page-Id"], h.get("WARC-Target-URI"), int(h["X-Payload-Length"]) if revisit else c["size"], noted if revisit else c["digest"], h["WARC-Type"], number["X-Refers-To-Page-Id"]))
                    if len(rows) > 10_000:
                        yield batch()
                        rows = []
        if rows:
            yield batch()

    listed = spark.createDataFrame([(f,) for f in files], "file string").repartition(min(len(files), shuffle_partitions(spark)))
    return listed.mapInArrow(run, schema)


def round_trip(pages: DataFrame, **options) -> DataFrame:
    spark = pages.sparkSession
    folder = fresh_path(spark, "warc")
    return read(spark, folder, write(chunks(decided(pages, **options)), folder), id_type(pages.schema[options.get("page_id", "page_id")].dataType))
