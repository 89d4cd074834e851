"""Token-id files in bit planes.

A shard holds the ids of a range of documents. Ids are cut into blocks of fixed size; a block is transposed into byte
planes (all lowest bytes, then all second bytes, and so on), or further into 32 bit planes, and each plane is compressed
by itself with zstandard, so that the nearly constant high planes take no room. The chunk index at the end of the shard
gives every block's place and plane lengths, and the document index the number of ids of each document, so any block
or document can be read without the rest.

Layout: magic; blocks; index; footer. The index is zstandard-compressed little-endian 64-bit integers: for each block
its offset and its planes' lengths; then the documents' lengths. The footer has the numbers of blocks, documents, ids,
the block size, the number of planes, the index's offset and length, its crc32, and the magic again.

Shards are made from a range partitioning by doc_id. A task writes its shard under a name of its own and renames it, so a
task that is run again, or twice at a time, leaves one whole shard. The folder is below the shared one that the session
names and can be in any store that pyarrow's filesystems reach.

Defined results: null text has the end id alone; a null doc_id comes first; rows that repeat a doc_id follow each other,
by text; ids may be whole numbers or strings (by code point); a very long text is one slice of its own in a worker, and its
blocks are written as they fill; other columns, whatever their names, are not read; an empty table makes no shard.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import encoding
from .scratch import fresh_path, shuffle_partitions

MAGIC = b"TOKPLN01"
BLOCK_IDS = 1 << 16
LEVEL = 3
_FOOTER = "<QQQQQQQQ8s"


def to_planes(ids: np.ndarray, bits: bool = False) -> list[bytes]:
    """Byte planes of 32-bit ids, lowest first; with ``bits`` 32 bit planes, lowest first."""
    planes = np.ascontiguousarray(ids.astype("<u4", copy=False)).view(np.uint8).reshape(-1, 4).T
    if not bits:
        return [p.tobytes() for p in planes]
    return [np.packbits((p >> b) & 1, bitorder="little").tobytes() for p in planes for b in range(8)]


def from_planes(planes: list[bytes], n: int, bits: bool = False) -> np.ndarray:
    if bits:
        each = [np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little") for p in planes]
        planes = [np.bitwise_or.reduce([each[8 * k + b] << b for b in range(8)]).astype(np.uint8).tobytes() for k in range(4)]
    out = np.empty((n, 4), np.uint8)
    for k, p in enumerate(planes):
        out[:, k] = np.frombuffer(p, np.uint8)
    return out.reshape(-1).view("<u4")


class Writer:
    """Streams ids into one shard; memory holds one block."""

    def __init__(self, out, block_ids: int = BLOCK_IDS, bits: bool = False):
        import zstandard

        self.out, self.block_ids, self.bits = out, block_ids, bits
        self.compress = zstandard.ZstdCompressor(level=LEVEL).compress
        self.blocks, self.lengths, self.waiting, self.n_waiting, self.n_ids, self.at = [], [], [], 0, 0, 0
        self._put(MAGIC)

    def _put(self, data: bytes) -> None:
        self.out.write(data)
        self.at += len(data)

    def add(self, ids: np.ndarray, lengths: np.ndarray) -> None:
        """The ids of one or more whole documents."""
        self.lengths.append(np.asarray(lengths, np.int64))
        self.n_ids += len(ids)
        self.waiting.append(ids)
        self.n_waiting += len(ids)
        if self.n_waiting >= self.block_ids:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        ids = np.concatenate(self.waiting) if self.waiting else np.zeros(0, "<u4")
        whole = len(ids) if last else len(ids) - len(ids) % self.block_ids
        for lo in range(0, whole, self.block_ids):
            planes = [self.compress(p) for p in to_planes(ids[lo : min(lo + self.block_ids, whole)], self.bits)]
            self.blocks.append([self.at, *map(len, planes)])
            self._put(b"".join(planes))
        self.waiting = [ids[whole:]]
        self.n_waiting = len(ids) - whole

    def close(self) -> None:
        self._flush(True)
        lengths = np.concatenate(self.lengths) if self.lengths else np.zeros(0, np.int64)
        flat = np.concatenate([np.asarray(self.blocks, np.int64).ravel(), lengths]).astype("<i8")
        index = self.compress(flat.tobytes())
        start = self.at
        self._put(index)
        self._put(struct.pack(_FOOTER, len(self.blocks), len(lengths), self.n_ids, self.block_ids, 32 if self.bits else 4, start, len(index), zlib.crc32(index), MAGIC))


class Reader:
    """Random access to a shard through a seekable file."""

    def __init__(self, file):
        import zstandard

        self.file, self.decompress = file, zstandard.ZstdDecompressor().decompress
        size = file.size()
        file.seek(size - struct.calcsize(_FOOTER))
        n_blocks, n_docs, self.n_ids, self.block_ids, self.planes, start, length, crc, magic = struct.unpack(_FOOTER, file.read(struct.calcsize(_FOOTER)))
        file.seek(start)
        index = file.read(length)
        if magic != MAGIC or zlib.crc32(index) != crc:
            raise ValueError("not a whole token shard")
        flat = np.frombuffer(self.decompress(index), "<i8")
        wide = n_blocks * (1 + self.planes)
        self.blocks, self.lengths = flat[:wide].reshape(n_blocks, 1 + self.planes), flat[wide:]
        assert len(self.lengths) == n_docs

    def block(self, k: int) -> np.ndarray:
        at, *sizes = self.blocks[k].tolist()
        n = min(self.block_ids, self.n_ids - k * self.block_ids)
        self.file.seek(at)
        data = self.file.read(sum(sizes))
        ends = np.cumsum([0, *sizes])
        return from_planes([self.decompress(data[a:b]) for a, b in zip(ends, ends[1:], strict=False)], n, self.planes == 32)

    def documents(self) -> Iterator[np.ndarray]:
        """The ids of each document in order; memory holds one block and one document."""
        rest, k = np.zeros(0, "<u4"), 0
        for n in self.lengths.tolist():
            have, total = [rest], len(rest)
            while total < n:
                have.append(self.block(k))
                total += len(have[-1])
                k += 1
            joined = np.concatenate(have) if len(have) > 1 else rest
            yield joined[:n]
            rest = joined[n:]


def id_type(kind: T.DataType) -> str:
    """The type of ids as files give them back: whole numbers as long, all else as string."""
    return "long" if isinstance(kind, T.IntegralType) else "string"


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write(docs: DataFrame, folder: str, tokenizer: str, end_id: int, text: str = "text", doc_id: str = "doc_id", bits: bool = False, block_ids: int = BLOCK_IDS) -> list[dict]:
    """Writes the shards and returns one entry per shard, in order: shard, file, n_docs, n_ids, and each shard's first place ``start``."""
    spark = docs.sparkSession
    picked = docs.select(F.col(f"`{doc_id}`").cast(id_type(docs.schema[doc_id].dataType)).alias("doc_id"), F.col(f"`{text}`").alias("_text"))
    sorted_ = picked.repartitionByRange(shuffle_partitions(spark), "doc_id").sortWithinPartitions("doc_id", F.xxhash64("_text"))
    kind = pa.int64() if isinstance(picked.schema["doc_id"].dataType, T.LongType) else pa.string()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard = TaskContext.get().partitionId()
        fs, path = _open(folder)
        fs.create_dir(path, recursive=True)
        writer = None
        name = f"shard-{shard:06d}"
        ids = []
        for b, flat, bounds in encoding.encoded(batches, tokenizer, end_id):
            if writer is None:
                temporary = f"{path}/_{name}-{uuid.uuid4().hex}"
                out = fs.open_output_stream(temporary)
                writer = Writer(out, block_ids, bits)
            writer.add(flat, np.diff(bounds))
            ids.append(b.column(0).cast(kind))
        if writer is not None:
            writer.close()
            out.close()
            keys = pa.table({"doc_id": pa.chunked_array(ids)})
            import pyarrow.parquet as pq

            pq.write_table(keys, f"{temporary}.ids", filesystem=fs)
            fs.move(f"{temporary}.ids", f"{path}/{name}.ids")
            fs.move(temporary, f"{path}/{name}.bin")
            yield pa.RecordBatch.from_pydict({"shard": [shard], "file": [name], "n_docs": [sum(map(len, ids))], "n_ids": [writer.n_ids]}, schema=pa.schema([("shard", pa.int32()), ("file", pa.string()), ("n_docs", pa.int64()), ("n_ids", pa.int64())]))

    shards = sorted((r.asDict() for r in sorted_.mapInArrow(run, "shard int, file string, n_docs long, n_ids long").collect()), key=lambda r: r["shard"])  # one row per shard
    start = 0
    for s in shards:
        s["start"] = start
        start += s["n_ids"]
    return shards


def read(spark: SparkSession, folder: str, shards: list[dict], id_type: str = "long") -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32."""
    schema = f"doc_id {id_type}, start long, n_tokens long, ids_crc32 long"
    if not shards:
        return spark.createDataFrame([], schema)
    listed = spark.createDataFrame([(s["file"], s["start"]) for s in shards], "file string, start long").repartition(min(len(shards), shuffle_partitions(spark)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.parquet as pq

        fs, path = _open(folder)
        for b in batches:
            for name, start in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                ids = pq.read_table(f"{path}/{name}.ids", filesystem=fs)["doc_id"].combine_chunks()
                with fs.open_input_file(f"{path}/{name}.bin") as f:
                    reader = Reader(f)
                    crcs = np.fromiter((encoding.crc32(d) for d in reader.documents()), np.int64, len(reader.lengths))
                starts = start + np.concatenate([[0], np.cumsum(reader.lengths)[:-1]])
                for lo in range(0, len(ids), 50_000):
                    part = slice(lo, lo + 50_000)
                    yield pa.RecordBatch.from_arrays([ids[part], pa.array(starts[part]), pa.array(reader.lengths[part]), pa.array(crcs[part])], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return listed.mapInArrow(run, schema)


def round_trip(docs: DataFrame, tokenizer: str, end_id: int = 2, **options) -> DataFrame:
    folder = fresh_path(docs.sparkSession, "token-files")
    return read(docs.sparkSession, folder, write(docs, folder, tokenizer, end_id, **options), id_type(docs.schema[options.get("doc_id", "doc_id")].dataType))
