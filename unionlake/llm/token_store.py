"""Token ids in files of independent zstandard frames with a trailing seek table.

A shard file is one frame per document, in ascending id order, then a skippable frame with the ids
of the documents, then the seek table in the public seekable format: a skippable frame with the
compressed and raw size of every frame before it and the low half of its raw bytes' xxh64. Any
zstandard reader can decompress the whole file and any reader of seekable files can seek in it;
ours reads the table first and then only the frames it was asked for, and checks each one. Ids are
stored in 16 bits where the vocabulary allows, else 32. The manifest lies beside the shards.

Defined results: a null text is empty; rows with a null id come first; rows that repeat an id are
each a document, ordered by text; an empty table gives no shard and no row; extra columns are ignored.
"""

from __future__ import annotations

import io
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unionlake.llm.common import light, partitions_for, portions, shared_folder
from unionlake.llm.tokens import encoder, tokenizer_path, with_end

#: Fixed values of the seekable format: magic numbers of its skippable frame and of the footer, the flag for
#: checksums; and the magic number of the skippable frame that holds our ids.
SEEK_FRAME, SEEKABLE, CHECKSUMS, ID_FRAME = 0x184D2A5E, 0x8F92EAB1, 0x80, 0x184D2A50
_HEAD = struct.Struct("<II")  # magic, bytes that follow
_ENTRY = struct.Struct("<III")  # compressed bytes, raw bytes, low half of the xxh64
_FOOTER = struct.Struct("<IBI")  # frames, flags, magic
_OWNER = struct.Struct("<Bq")  # 1 if there is an id, id


class ShardWriter:
    def __init__(self, sink, width: int = 2, level: int = 3):
        self.sink, self.width, self.entries, self.owners, self.n_ids = sink, width, [], [], 0
        self.packer = zstandard.ZstdCompressor(level=level, write_checksum=True)

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        """ids: little-endian, of the shard's width."""
        frame = self.packer.compress(ids)
        self.sink.write(frame)
        self.entries.append(_ENTRY.pack(len(frame), ids.nbytes, xxhash.xxh64_intdigest(ids) & 0xFFFFFFFF))
        self.owners.append(_OWNER.pack(doc_id is not None, doc_id or 0))
        self.n_ids += len(ids)

    def finish(self) -> None:
        owners = b"".join([bytes([self.width]), *self.owners])
        self.sink.write(_HEAD.pack(ID_FRAME, len(owners)) + owners)
        entries = [*self.entries, _ENTRY.pack(_HEAD.size + len(owners), 0, xxhash.xxh64_intdigest(b"") & 0xFFFFFFFF)]
        table = b"".join([*entries, _FOOTER.pack(len(entries), CHECKSUMS, SEEKABLE)])
        self.sink.write(_HEAD.pack(SEEK_FRAME, len(table)) + table)


class ShardReader:
    """Random access to a shard: frames are read, decompressed and checked one by one."""

    def __init__(self, source):
        self.source = source
        end = source.seek(0, io.SEEK_END) - _FOOTER.size
        source.seek(end)
        n, flags, magic = _FOOTER.unpack(source.read(_FOOTER.size))
        if (flags, magic) != (CHECKSUMS, SEEKABLE):
            raise ValueError("no seek table at the end of the file")
        source.seek(end - n * _ENTRY.size)
        rows = list(_ENTRY.iter_unpack(source.read(n * _ENTRY.size)))
        self.offsets = np.concatenate(([0], np.cumsum([r[0] for r in rows], dtype=np.int64))).tolist()
        self.sizes, self.raw_sizes, self.sums = (list(c)[:-1] for c in zip(*rows, strict=True))
        source.seek(self.offsets[-2])
        magic, size = _HEAD.unpack(source.read(_HEAD.size))
        if magic != ID_FRAME or size != 1 + (n - 1) * _OWNER.size:
            raise ValueError("the file does not name its documents")
        self.width = source.read(1)[0]
        self.doc_ids = [d if there else None for there, d in _OWNER.iter_unpack(source.read(size - 1))]
        self.unpacker = zstandard.ZstdDecompressor()

    def frame(self, i: int) -> np.ndarray:
        self.source.seek(self.offsets[i])
        raw = self.unpacker.decompress(self.source.read(self.sizes[i]))
        if len(raw) != self.raw_sizes[i] or xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != self.sums[i]:
            raise ValueError(f"frame {i} does not match its entry in the seek table")
        return np.frombuffer(raw, f"<u{self.width}")

    def documents(self, wanted: set[int] | None = None) -> Iterator[tuple[int | None, np.ndarray]]:
        for i, d in enumerate(self.doc_ids):
            if wanted is None or d in wanted:
                yield d, self.frame(i)


def write_shards(spark: SparkSession, docs: DataFrame, folder: str | None = None, end_id: int = 2, tokenizer: str | None = None, shard_bytes: int = 16 << 20) -> list[dict]:
    """Writes all documents; returns the manifest, a row per shard in id order (path, documents, ids before it), which is also written as manifest.json.

    A task writes under a name of its own and renames at the end, so a task that is run again
    leaves no half-written shard, and only the attempt that Spark took is in the manifest.
    """
    folder, path = folder or shared_folder(spark, "tokens"), tokenizer or tokenizer_path()
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text"))
    shards = partitions_for(rows, "text", shard_bytes)
    rows = rows.repartitionByRange(shards, "doc_id", F.xxhash64("text")) if shards > 1 else rows.coalesce(1)
    rows = rows.sortWithinPartitions("doc_id", "text")

    def write(batches):
        from pyspark import TaskContext

        enc, part = encoder(path), TaskContext.get().partitionId()
        width = 2 if max(enc.lib.get_vocab_size(), end_id + 1) <= 1 << 16 else 4
        fs, root = pafs.FileSystem.from_uri(folder)
        fs.create_dir(root, recursive=True)
        name, writer, sink = f"{root}/shard-{part:06d}-{uuid.uuid4().hex[:8]}.zst", None, None
        for batch in batches:
            for piece in portions(batch, 1):
                ids, bounds = with_end(*enc.encode(piece.column(1)), end_id)
                ids = ids.astype(f"<u{width}")
                for i, doc_id in enumerate(piece.column(0).to_pylist()):
                    if writer is None:
                        sink = fs.open_output_stream(name + ".part")
                        writer = ShardWriter(sink, width)
                    writer.add(doc_id, ids[bounds[i] : bounds[i + 1]])
        if writer is not None:
            writer.finish()
            sink.close()
            fs.move(name + ".part", name)
            yield pa.RecordBatch.from_pydict({"part": [part], "name": [name.rsplit("/", 1)[1]], "n_docs": [len(writer.entries)], "n_ids": [writer.n_ids]})

    manifest, before = [], 0
    for r in sorted(rows.mapInArrow(light(write), "part bigint, name string, n_docs bigint, n_ids bigint").collect()):  # a row per shard
        manifest.append({"path": f"{folder}/{r['name']}", "n_docs": r["n_docs"], "n_ids": r["n_ids"], "ids_before": before})
        before += r["n_ids"]
    fs, root = pafs.FileSystem.from_uri(folder)
    fs.create_dir(root, recursive=True)
    with fs.open_output_stream(f"{root}/manifest.json") as f:
        f.write(json.dumps(manifest).encode())
    return manifest


def read_report(spark: SparkSession, manifest: list[dict]) -> DataFrame:
    """Every document as the files have it: (doc_id, start, n_tokens, ids_crc32)."""
    schema = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint"
    if not manifest:
        return spark.createDataFrame([], schema)

    def read(batches):
        for batch in batches:
            for path, start in zip(*(batch.column(i).to_pylist() for i in range(2)), strict=True):
                fs, name = pafs.FileSystem.from_uri(path)
                out = []
                with fs.open_input_file(name) as f:
                    for doc_id, ids in ShardReader(f).documents():
                        out.append((doc_id, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                        start += len(ids)
                        if len(out) == 20_000:
                            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["doc_id", "start", "n_tokens", "ids_crc32"])
                            out = []
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["doc_id", "start", "n_tokens", "ids_crc32"])

    files = spark.createDataFrame([(m["path"], m["ids_before"]) for m in manifest], "path string, start bigint")
    return files.repartition(len(manifest)).mapInArrow(light(read), schema)


def round_trip(spark: SparkSession, docs: DataFrame) -> DataFrame:
    return read_report(spark, write_shards(spark, docs))
