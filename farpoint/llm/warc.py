"""WARC archives as seekable Zstandard bundles.

Each record is an independent Zstandard frame; a bundle ends with a skippable frame that holds a seek table (compressed and
plain size of every frame, then their number and a magic number, as in the published seekable format). An index maps
record identifiers to (bundle file, frame, offset from the bundle's start, compressed size), so one record is read by one range request.

Records with equal payloads of at least ``smallest`` bytes are stored once: the one with the largest id is the response, the
others are revisit records without a payload that refer to it. Which are equal is decided from digests: the payloads
themselves move once, to the tasks that write, and a digest that many records share is split by Spark's skewed-join handling.

Bundles are written by the executors through the URI's own file system (local, HDFS, S3) under names that contain a random
part, and only those that the committed index names count: files of lost or repeated tasks are never read. For schemes that
the executors' file-system library does not know, bundles become rows of a Parquet table instead (``as_files=False``).

Defined results: a null payload is empty; a null id is written as such and ranks below all others; rows with equal id and payload are
all responses if that id is the largest; null urls leave the target header out; control characters in urls are
percent-encoded; an empty table gives an empty archive; further columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from farpoint.session import fresh_path, ship

#: Fixed values of the seekable format: skippable-frame magic, seek-table magic.
SKIPPABLE, SEEKABLE = 0x184D2A5E, 0x8F92EAB1
#: A bundle is closed at so many compressed bytes.
BUNDLE_BYTES = 8 << 20
NO_KEY = "<urn:null-record>"
DATE = "2024-01-01T00:00:00Z"
INDEX = "record_id {kind}, bundle string, frame int, offset long, size long"


def seek_table(frames: list[tuple[int, int]]) -> bytes:
    body = b"".join(struct.pack("<II", c, d) for c, d in frames) + struct.pack("<IBI", len(frames), 0, SEEKABLE)
    return struct.pack("<II", SKIPPABLE, len(body)) + body


def read_seek_table(bundle: bytes) -> list[tuple[int, int, int]]:
    """(offset, compressed size, plain size) of every frame."""
    n, flags, magic = struct.unpack("<IBI", bundle[-9:])
    if magic != SEEKABLE:
        raise ValueError("no seek table")
    entry = 12 if flags & 0x80 else 8
    at, out = len(bundle) - 9 - n * entry, []
    if struct.unpack("<II", bundle[at - 8 : at]) != (SKIPPABLE, n * entry + 9):
        raise ValueError("damaged seek table")
    offset = 0
    for i in range(n):
        c, d = struct.unpack_from("<II", bundle, at + i * entry)
        out.append((offset, c, d))
        offset += c
    return out


def identifier(key) -> str:
    """A null key has an identifier that no other key can spell."""
    return f"<urn:record:{key}>" if key is not None else NO_KEY


def record(key, url: str | None, payload: bytes, n: int, digest: str, refers_to) -> bytes:
    """One WARC 1.1 record, a response with its payload or a revisit of another record."""
    revisit = refers_to is not None
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % n
    block = http + (b"" if revisit else payload)
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: {identifier(key)}", f"WARC-Date: {DATE}"]
    if url is not None:
        head.append("WARC-Target-URI: " + quote(url, safe="%/:=&?~#+!$,;'@()*[]"))
    head.append("WARC-Payload-Digest: sha1:" + base64.b32encode(bytes.fromhex(digest)).decode())
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {identifier(refers_to)}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}", "", ""]
    return "\r\n".join(head).encode() + block + b"\r\n\r\n"


def parse(data: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """(WARC headers, HTTP headers, payload), header names in lower case."""
    head, _, rest = data.partition(b"\r\n\r\n")
    fields = lambda raw: {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in raw.decode().split("\r\n")[1:])}
    warc = fields(head)
    block = rest[: int(warc["content-length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    return warc, fields(http), payload


class _Bundles:
    """Collects frames and hands out closed bundles."""

    def __init__(self):
        import zstandard

        self.zstd = zstandard.ZstdCompressor(level=3)
        self.clear()

    def clear(self):
        self.parts, self.frames, self.keys, self.at = [], [], [], 0

    def add(self, key, data: bytes) -> None:
        frame = self.zstd.compress(data)
        self.keys.append((key, len(self.frames), self.at, len(frame)))
        self.frames.append((len(frame), len(data)))
        self.parts.append(frame)
        self.at += len(frame)

    def close(self) -> tuple[bytes, list]:
        out = b"".join(self.parts) + seek_table(self.frames), self.keys
        self.clear()
        return out


def _plan(pages: DataFrame, key: str, url: str, payload: str, smallest: int) -> DataFrame:
    """(record_id, url, payload, n, digest, refers_to): refers_to is set on revisits, whose payload is null."""
    body = F.encode(F.coalesce(F.col(payload), F.lit("")), "utf-8")
    rows = pages.select(F.col(key).alias("record_id"), F.col(url).cast("string").alias("url"), body.alias("payload"))
    rows = rows.withColumn("n", F.octet_length("payload").cast("long")).withColumn("digest", F.sha1("payload"))
    heads = rows.where(F.col("n") >= smallest).groupBy(F.col("digest").alias("h_digest"), F.col("n").alias("h_n")).agg(F.max("record_id").alias("head"), F.count("*").alias("copies")).where("copies > 1")
    joined = rows.join(heads, (F.col("digest") == F.col("h_digest")) & (F.col("n") == F.col("h_n")), "left")
    refers = F.when(~F.col("record_id").eqNullSafe(F.col("head")), F.col("head"))
    return joined.withColumn("refers_to", refers).select("record_id", "url", F.when(F.col("refers_to").isNull(), F.col("payload")).alias("payload"), "n", "digest", "refers_to")


def write_archive(pages: DataFrame, folder: str | None = None, key: str = "page_id", url: str = "url", payload: str = "html", smallest: int = 1000, as_files: bool = True) -> tuple[str, DataFrame]:
    """Write all rows as bundles under folder (default: the shared folder); gives it and the index, itself written there."""
    spark = ship(pages.sparkSession)
    folder = folder or fresh_path(spark, "warc")
    kind = pages.schema[key].dataType
    store = f"{folder}/bundles"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        out, arrow_kind = _Bundles(), None
        files, root = fs.FileSystem.from_uri(store) if as_files else (None, None)

        def flush() -> pa.RecordBatch:
            name = f"{uuid.uuid4().hex}.warc.zst"
            data, keys = out.close()
            if as_files:
                files.create_dir(root, recursive=True)
                with files.open_output_stream(f"{root}/{name}.part") as f:
                    f.write(data)
                files.move(f"{root}/{name}.part", f"{root}/{name}")
            cols = list(zip(*keys))
            body = [None if as_files else data] + [None] * (len(keys) - 1)
            return pa.RecordBatch.from_arrays([pa.array(cols[0], arrow_kind), pa.array([name] * len(keys)), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64()), pa.array(body, pa.binary())], names=["record_id", "bundle", "frame", "offset", "size", "body"])

        for b in batches:
            arrow_kind = b.schema.field(0).type
            for i in range(b.num_rows):
                k, u, p, n, d, r = (c[i].as_py() for c in b.columns)
                out.add(k, record(k, u, p or b"", n, d, r))
                if out.at >= BUNDLE_BYTES:
                    yield flush()
        if out.keys:
            yield flush()

    rows = _plan(pages, key, url, payload, smallest)
    made = rows.mapInArrow(run, INDEX.format(kind=kind.simpleString()) + ", body binary")
    made.write.parquet(f"{folder}/index")
    return folder, spark.read.schema(T.StructType.fromDDL(INDEX.format(kind=kind.simpleString()))).parquet(f"{folder}/index")


def read_archive(spark, folder: str, index: DataFrame, as_files: bool = True, null_id: str | None = "null") -> DataFrame:
    """Every record that the index names, read back through the seek tables: record_id as text (null_id for a null one), record_type, refers_to as text, payload_bytes, payload_digest, payload, url."""
    ship(spark)
    if as_files:
        named = index.select("bundle").distinct()
        n = named.count()
        # Names only are dealt out; each task opens its bundles itself.
        found = named.repartition(max(1, min(n, 100_000)))
    else:
        found = spark.read.schema("bundle string, body binary").parquet(f"{folder}/index").where("body is not null").select("body")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard
        from pyarrow import fs

        zstd = zstandard.ZstdDecompressor()
        files, root = fs.FileSystem.from_uri(f"{folder}/bundles") if as_files else (None, None)
        bare = lambda x: None if x is None else null_id if x == NO_KEY else x[len("<urn:record:") : -1]
        for b in batches:
            for body in b.column(0):
                if as_files:
                    with files.open_input_file(f"{root}/{body.as_py()}") as f:
                        data = f.read()
                else:
                    data = body.as_py()
                view, rows = memoryview(data), []
                for offset, size, plain in read_seek_table(data):
                    warc, http, payload = parse(zstd.decompress(view[offset : offset + size], max_output_size=plain))
                    digest = base64.b32decode(warc["warc-payload-digest"].removeprefix("sha1:")).hex()
                    revisit = warc["warc-type"] == "revisit"
                    if not revisit and (hashlib.sha1(payload).hexdigest() != digest or len(payload) != int(http["content-length"])):
                        raise ValueError(f"damaged record {warc['warc-record-id']}")
                    rows.append((bare(warc["warc-record-id"]), warc["warc-type"], bare(warc.get("warc-refers-to")), int(http["content-length"]), digest, None if revisit else payload, warc.get("warc-target-uri")))
                    if len(rows) >= 256:
                        yield _batch(rows)
                        rows = []
                if rows:
                    yield _batch(rows)

    return found.mapInArrow(run, "record_id string, record_type string, refers_to string, payload_bytes long, payload_digest string, payload binary, url string")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.string(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.binary(), pa.string()]
    names = ["record_id", "record_type", "refers_to", "payload_bytes", "payload_digest", "payload", "url"]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names)


def read_record(folder: str, bundle: str, offset: int, size: int) -> tuple[dict[str, str], dict[str, str], bytes]:
    """One record by its place in the index: a single range request."""
    import zstandard
    from pyarrow import fs

    files, root = fs.FileSystem.from_uri(f"{folder}/bundles")
    with files.open_input_file(f"{root}/{bundle}") as f:
        f.seek(offset)
        return parse(zstandard.ZstdDecompressor().decompress(f.read(size)))
