"""WARC archives: records written with deduplication and segmentation, and reassembled on reading.

Of pages with equal payloads of at least `revisit_bytes`, the one with the largest id is the
response and the others are revisits of it. Responses carry an HTTP block in chunked transfer
framing; a block longer than `segment_bytes` is cut into a first record and continuation records.
Reading groups the segments of a record by the identifier of its origin, orders them by segment
number, checks the total length that the last one states and decodes the chunks.

Defined results: null html is an empty payload; pages that repeat an id are each a record, and of
equal ids with equal payloads one is the response; rows with a null id are responses; an empty
table writes nothing and gives an empty result; a url's blanks, control characters and letters
beyond ASCII are percent-encoded in headers; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unionlake.llm.common import light, shared_folder

PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
SEGMENTS = "origin string, number int, last boolean, total bigint, page_id bigint, kind string, refers_to bigint, said_digest string, block binary"
REPORT = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint"


def chunked(payload: bytes, size: int = 8192) -> bytes:
    out = [b"%x\r\n%b\r\n" % (len(c), c) for c in (payload[i : i + size] for i in range(0, len(payload), size))]
    return b"".join([*out, b"0\r\n\r\n"])


def unchunked(body: bytes) -> bytes:
    out, at = [], 0
    while True:
        end = body.index(b"\r\n", at)
        n = int(body[at:end].split(b";")[0], 16)
        if n == 0:
            return b"".join(out)
        if body[end + 2 + n : end + 4 + n] != b"\r\n":
            raise ValueError("a chunk does not end where its size says")
        out.append(body[end + 2 : end + 2 + n])
        at = end + 4 + n


def record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    """One record as a gzip member of its own."""
    head = "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", str(len(block)))])
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    return packer.compress(b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n") + packer.flush()


def records(source, piece: int = 1 << 20) -> Iterator[tuple[dict[str, str], bytes]]:
    """The records of an archive, one gzip member at a time."""
    rest = b""
    while True:
        unpacker, out = zlib.decompressobj(31), []
        while not unpacker.eof:
            rest = rest or source.read(piece)
            if not rest:
                if out:
                    raise ValueError("the archive ends inside a record")
                return
            out.append(unpacker.decompress(rest))
            rest = unpacker.unused_data
        raw = b"".join(out)
        head, _, body = raw.partition(b"\r\n\r\n")
        lines = head.decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError("not a WARC record")
        headers = {k.lower(): v for k, v in (x.split(": ", 1) for x in lines[1:])}
        n = int(headers["content-length"])
        if body[n:] != b"\r\n\r\n":
            raise ValueError("a record is not as long as it says")
        yield headers, body[:n]


def header_value(url: str) -> str:
    """The url with blanks, control characters and what is not ASCII percent-encoded, so that it is one header line."""
    return quote(url, safe="".join(map(chr, range(33, 127))), errors="replace")


def page_records(page_id: int | None, url: str, payload: bytes, digest: str, refers_to: int | None, revisit: bool, segment_bytes: int) -> list[tuple[list[tuple[str, str]], bytes]]:
    own = f"<urn:uuid:{uuid.uuid4()}>"
    common = [("WARC-Date", "2024-01-01T00:00:00Z"), ("WARC-Target-URI", header_value(url))]
    common += [("X-Page-ID", str(page_id))] if page_id is not None else []
    digests = [("WARC-Payload-Digest", f"sha1:{digest}")]
    kind = [("Content-Type", "application/http; msgtype=response")]
    if revisit:
        block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
        more = [("WARC-Profile", PROFILE), ("X-Refers-To-Page-ID", str(refers_to))]
        return [([("WARC-Type", "revisit"), ("WARC-Record-ID", own), *common, *digests, *more, *kind], block)]
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(payload)
    cuts = [block[i : i + segment_bytes] for i in range(0, len(block), segment_bytes)]
    if len(cuts) == 1:
        return [([("WARC-Type", "response"), ("WARC-Record-ID", own), *common, *digests, *kind], block)]
    out = [([("WARC-Type", "response"), ("WARC-Record-ID", own), *common, *digests, ("WARC-Segment-Number", "1"), *kind], cuts[0])]
    for i, c in enumerate(cuts[1:], 2):
        more = [("WARC-Segment-Origin-ID", own), ("WARC-Segment-Number", str(i))]
        more += [("WARC-Segment-Total-Length", str(len(block)))] if i == len(cuts) else []
        out.append(([("WARC-Type", "continuation"), ("WARC-Record-ID", f"<urn:uuid:{uuid.uuid4()}>"), *common, *more], c))
    return out


def _payload() -> Column:
    return F.encode(F.coalesce(F.col("html"), F.lit("")), "UTF-8")


def revisits(pages: DataFrame, revisit_bytes: int = 1000) -> DataFrame:
    """(page_id, copy_key, refers_to): pages whose payload an equal page with a larger id holds.

    Works on digests and ids alone; payloads do not move.
    """
    light = pages.where(F.octet_length(_payload()) >= revisit_bytes).where("page_id is not null")
    light = light.select("page_id", F.sha2(_payload(), 256).alias("copy_key"))
    last = light.groupBy("copy_key").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1")
    return light.distinct().join(last.drop("n"), "copy_key").where("page_id < refers_to")


def write_archives(spark: SparkSession, pages: DataFrame, folder: str | None = None, revisit_bytes: int = 1000, segment_bytes: int = 32 << 10, archive_bytes: int = 64 << 20) -> list[str]:
    """Writes archives of about archive_bytes and returns the paths. A task writes under names of its own and renames each archive at its end."""
    folder = folder or shared_folder(spark, "warc")
    pages = pages.select(F.col("page_id").cast("bigint").alias("page_id"), "url", "html")
    again = revisits(pages, revisit_bytes).withColumnsRenamed({"page_id": "_id", "copy_key": "_key"})
    rows = pages.join(again, (F.col("page_id") == F.col("_id")) & (F.sha2(_payload(), 256) == F.col("_key")), "left")
    rows = rows.select("page_id", "url", _payload().alias("payload"), F.sha1(_payload()).alias("digest"), "refers_to")

    def write(batches):
        fs, root = pafs.FileSystem.from_uri(folder)
        fs.create_dir(root, recursive=True)
        name, sink, done = "", None, []

        def close():
            sink.close()
            fs.move(name + ".part", name)
            done.append(name.rsplit("/", 1)[1])

        for batch in (b.slice(at, 256) for b in batches for at in range(0, b.num_rows, 256)):
            for r in batch.to_pylist():
                if sink is None:
                    name = f"{root}/part-{uuid.uuid4().hex}.warc.gz"
                    sink = fs.open_output_stream(name + ".part", compression=None)
                for headers, block in page_records(r["page_id"], r["url"] or "urn:none", r["payload"], r["digest"], r["refers_to"], r["refers_to"] is not None, segment_bytes):
                    sink.write(record(headers, block))
                if sink.tell() > archive_bytes:
                    close()
                    sink = None
        if sink is not None:
            close()
        if done:
            yield pa.RecordBatch.from_pydict({"name": done})

    return sorted(f"{folder}/{r['name']}" for r in rows.mapInArrow(light(write), "name string").collect())  # a name per archive


def read_segments(spark: SparkSession, paths: list[str]) -> DataFrame:
    """Every record of the archives, with the origin it belongs to and its place there."""

    def read(batches):
        names = [f.split()[0] for f in SEGMENTS.split(", ")]
        kinds = [pa.string(), pa.int32(), pa.bool_(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.binary()]

        def batch_of(out):
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names)

        for batch in batches:
            for path in batch.column(0).to_pylist():
                fs, name = pafs.FileSystem.from_uri(path)
                out, size = [], 0
                with fs.open_input_stream(name, compression=None) as f:
                    for h, block in records(f):
                        number = h.get("warc-segment-number")
                        total, page, refers = (int(h[k]) if k in h else None for k in ("warc-segment-total-length", "x-page-id", "x-refers-to-page-id"))
                        origin = h.get("warc-segment-origin-id", h["warc-record-id"])
                        out.append((origin, int(number or 1), number is None or total is not None, total, page, h["warc-type"], refers, h.get("warc-payload-digest", "").removeprefix("sha1:"), block))
                        size += len(block)
                        if size > 16 << 20:
                            yield batch_of(out)
                            out, size = [], 0
                if out:
                    yield batch_of(out)

    if not paths:
        return spark.createDataFrame([], SEGMENTS)
    return spark.createDataFrame([(p,) for p in paths], "path string").repartition(len(paths)).mapInArrow(light(read), SEGMENTS)


def reassemble(segments: DataFrame) -> DataFrame:
    """(page_id, kind, refers_to, said_digest, block) of whole records; a record that is cut or too short or long is an error.

    Only records in several segments are shuffled, by their origin; a group is one record.
    """
    names = ["page_id", "kind", "refers_to", "said_digest", "block"]
    whole = segments.where("number = 1 and last").select(*names)
    parts = segments.where("not (number = 1 and last)")
    packed = parts.groupBy("origin").agg(
        F.array_sort(F.collect_list(F.struct("number", "block"))).alias("pieces"),
        F.max("total").alias("total"),
        *[F.max(F.when(F.col("number") == 1, F.col(c))).alias(c) for c in names[:4]],
    )
    ordered = F.forall(F.sequence(F.lit(1), F.size("pieces")), lambda i: F.element_at("pieces", i)["number"] == i)
    block = F.aggregate("pieces", F.lit(b""), lambda a, p: F.concat(a, p["block"]))
    good = ordered & (F.octet_length("block") == F.col("total"))
    joined = packed.withColumn("block", block).withColumn("block", F.when(good, F.col("block")).otherwise(F.raise_error(F.concat(F.lit("segments missing or of wrong length: "), "origin")).cast("binary")))
    return whole.unionByName(joined.select(*names))


def payloads(recs: DataFrame) -> DataFrame:
    """The report of each record; a response's digest is taken from the decoded payload and held against the stated one."""

    def decode(batches):
        for batch in (b.slice(at, 256) for b in batches for at in range(0, b.num_rows, 256)):
            out = []
            for r in batch.to_pylist():
                head, _, body = r["block"].partition(b"\r\n\r\n")
                fields = {k.lower(): v for k, v in (x.split(": ", 1) for x in head.decode().split("\r\n")[1:])}
                if r["kind"] == "revisit":
                    out.append((r["page_id"], int(fields["content-length"]), r["said_digest"], "revisit", r["refers_to"]))
                    continue
                payload = unchunked(body) if fields.get("transfer-encoding") == "chunked" else body
                digest = hashlib.sha1(payload).hexdigest()
                if digest != r["said_digest"]:
                    raise ValueError(f"page {r['page_id']}: the payload does not match its digest")
                out.append((r["page_id"], len(payload), digest, "response", None))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
            columns = [pa.array([o[i] for o in out], k) for i, k in enumerate(kinds)]
            yield pa.RecordBatch.from_arrays(columns, [f.split()[0] for f in REPORT.split(", ")])

    return recs.mapInArrow(light(decode), REPORT)


def round_trip(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """Writes all pages as records, reads the archives back and reports what they hold."""
    return payloads(reassemble(read_segments(spark, write_archives(spark, pages))))
