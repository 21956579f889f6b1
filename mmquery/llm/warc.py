"""WARC archives of Zstandard frames: a writer, and a reader that validates what it reads.

A file starts with a skippable frame that holds the file's dictionary (plain, or itself a Zstandard frame); then every record is
one frame of its own, compressed with that dictionary, so records can be read one by one. Executors write files of
bounded size under names of their own into the shared folder and report them; only reported files are read, so what a
lost executor or a second attempt left behind doesn't count.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Magic number of the skippable frame that carries a dictionary.
DICTIONARY_FRAME = 0x184D2A5D
FRAME_MAGIC = struct.pack("<I", zstandard.MAGIC_NUMBER)
VERSION = b"WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "1970-01-01T00:00:00Z"
#: Uncompressed bytes after which a file is closed; records from which its dictionary is trained; the dictionary's bytes.
FILE_BYTES = 32 << 20
TRAIN_RECORDS, TRAIN_BYTES, DICTIONARY_BYTES = 64, 2 << 20, 16 << 10
CHUNK = 1 << 20


class WarcError(ValueError):
    """What the file holds isn't a valid record."""


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page_id: int | None) -> str:
    return f"<urn:x-page:{'' if page_id is None else page_id}>"


def page_of(urn: str) -> int | None:
    inner = urn.removeprefix("<urn:x-page:").removesuffix(">")
    return int(inner) if inner else None


def record(page_id: int | None, url: str | None, payload: bytes, own_digest: str, revisit: bool, refers_to: int | None) -> bytes:
    """One record: a response with its payload, or a revisit whose block is the HTTP header alone."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if revisit else http + payload
    clean = "".join(c for c in url or "about:blank" if c not in "\r\n")
    head = [
        ("WARC-Type", "revisit" if revisit else "response"),
        ("WARC-Record-ID", record_id(page_id)),
        ("WARC-Date", DATE),
        ("WARC-Target-URI", clean),
        ("WARC-Payload-Digest", f"sha1:{own_digest}"),
        ("WARC-Block-Digest", f"sha1:{digest(block)}"),
        ("Content-Type", "application/http; msgtype=response"),
    ]
    if revisit:
        head += [("WARC-Refers-To", record_id(refers_to)), ("WARC-Profile", PROFILE)]
    head.append(("Content-Length", str(len(block))))
    return VERSION + b"\r\n" + b"".join(f"{k}: {v}\r\n".encode() for k, v in head) + b"\r\n" + block + b"\r\n\r\n"


def _headers(raw: bytes) -> dict[str, str]:
    out = {}
    for line in raw.split(b"\r\n"):
        name, colon, value = line.partition(b":")
        if not colon or not name.strip():
            raise WarcError(f"no header line: {line[:80]!r}")
        out[name.decode().strip().lower()] = value.decode().strip()
    return out


def parse(raw: bytes) -> dict:
    """The fields of one record, after its headers, lengths and digests have been checked."""
    head, gap, rest = raw.partition(b"\r\n\r\n")
    first, _, lines = head.partition(b"\r\n")
    if not gap or not first.startswith(b"WARC/1."):
        raise WarcError("no WARC version line")
    h = _headers(lines)
    for name in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if name not in h:
            raise WarcError(f"{name} is missing")
    if not h["content-length"].isdigit() or len(rest) != int(h["content-length"]) + 4 or rest[-4:] != b"\r\n\r\n":
        raise WarcError("the block's length isn't Content-Length")
    block = rest[:-4]
    if "warc-block-digest" in h and h["warc-block-digest"] != f"sha1:{digest(block)}":
        raise WarcError("the block's digest differs")
    http, gap, payload = block.partition(b"\r\n\r\n")
    status, _, lines = http.partition(b"\r\n")
    if not gap or not status.startswith(b"HTTP/"):
        raise WarcError("the block is no HTTP response")
    size = _headers(lines).get("content-length", "")
    if not size.isdigit():
        raise WarcError("the payload's length is missing")
    kind, claimed = h["warc-type"], h.get("warc-payload-digest", "").removeprefix("sha1:")
    if kind == "response":
        if len(payload) != int(size):
            raise WarcError("the payload's length differs")
        if claimed != digest(payload):
            raise WarcError("the payload's digest differs")
    elif kind == "revisit":
        if payload or "warc-refers-to" not in h or not claimed:
            raise WarcError("a revisit needs a digest and a record it refers to, and no payload")
    else:
        raise WarcError(f"unexpected record type {kind}")
    return {"page_id": page_of(h["warc-record-id"]), "url": h.get("warc-target-uri"), "payload_bytes": int(size), "payload_digest": claimed, "record_type": kind, "refers_to": page_of(h["warc-refers-to"]) if kind == "revisit" else None, "payload": payload if kind == "response" else None}


def dictionary_of(samples: list[bytes]) -> zstandard.ZstdCompressionDict | None:
    """A trained dictionary; None where the samples are too few or too alike to train one."""
    if len(samples) < 8:
        return None
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples)
    except zstandard.ZstdError:
        return None


def write_archive(out, records: Iterator[bytes], dictionary: zstandard.ZstdCompressionDict | None) -> int:
    """Write the dictionary's frame and a frame for each record; returns how many records."""
    if dictionary is not None:
        raw = zstandard.ZstdCompressor(level=9).compress(dictionary.as_bytes())
        out.write(struct.pack("<II", DICTIONARY_FRAME, len(raw)) + raw)
    zip_ = zstandard.ZstdCompressor(level=3, dict_data=dictionary, write_content_size=True)
    n = 0
    for r in records:
        out.write(zip_.compress(r))
        n += 1
    return n


def read_archive(src, chunk: int = CHUNK) -> Iterator[bytes]:
    """The records of an archive, one frame each; src gives bytes by read(n). Memory: one record and a chunk."""
    held = b""

    def fill(least: int) -> bool:
        nonlocal held
        while len(held) < least:
            more = src.read(chunk)
            if not more:
                return False
            held += more
        return True

    dictionary = None
    if fill(8) and struct.unpack("<I", held[:4])[0] == DICTIONARY_FRAME:
        size = struct.unpack("<I", held[4:8])[0]
        if not fill(8 + size):
            raise WarcError("the dictionary's frame is cut off")
        raw, held = held[8 : 8 + size], held[8 + size :]
        if raw.startswith(FRAME_MAGIC):
            raw = zstandard.ZstdDecompressor().decompress(raw, max_output_size=64 << 20)
        dictionary = zstandard.ZstdCompressionDict(raw)
    unzip = zstandard.ZstdDecompressor(dict_data=dictionary)
    while held or fill(1):
        if not fill(4):
            raise WarcError("the archive ends within a frame")
        magic = struct.unpack("<I", held[:4])[0]
        if magic & 0xFFFFFFF0 == 0x184D2A50:  # any other skippable frame
            if not fill(8) or not fill(8 + struct.unpack("<I", held[4:8])[0]):
                raise WarcError("a skippable frame is cut off")
            held = held[8 + struct.unpack("<I", held[4:8])[0] :]
            continue
        if held[:4] != FRAME_MAGIC:
            raise WarcError("no Zstandard frame where one should start")
        one = unzip.decompressobj()
        parts = []
        while True:
            parts.append(one.decompress(held))
            if one.eof:
                held = one.unused_data
                break
            held = src.read(chunk)
            if not held:
                raise WarcError("the archive ends within a frame")
        yield b"".join(parts)


def _filesystem(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path.replace("file:/", "file:///", 1) if path.startswith("file:/") and not path.startswith("file://") else path)


def write(pages: DataFrame, folder: str | None = None, least_bytes: int = 0) -> DataFrame:
    """Write a record for every row of `pages` (page_id, url, html) and return the files: path, records, bytes.

    The payload is html in UTF-8 (null: empty). Of records with equal payloads of at least `least_bytes` bytes, that with the
    largest page_id is the response and the others revisit it; smaller payloads are always responses. Rows that repeat the
    largest page_id are all responses; null page_ids rank lowest, and among themselves are all responses. Extra columns are
    ignored; an empty table writes no file.
    """
    spark = common.bounded(pages).sparkSession
    folder = folder or f"{common.shared_dir(spark)}/mmquery/warc-{uuid.uuid4().hex}"
    slim = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"))
    slim = slim.withColumn("sha", F.sha1(F.encode("html", "UTF-8"))).withColumn("size", F.octet_length("html"))
    owners = common.materialise(slim.groupBy("sha", "size").agg(F.max("page_id").alias("owner")), "owners")
    met = slim.join(owners.withColumnRenamed("sha", "osha").withColumnRenamed("size", "osize"), (F.col("sha") == F.col("osha")) & (F.col("size") == F.col("osize")))
    revisit = (F.col("size") >= least_bytes) & ~F.col("page_id").eqNullSafe(F.col("owner"))
    rows = met.select("page_id", "url", F.when(revisit, F.lit(None)).otherwise(F.col("html")).alias("html"), "sha", "size", revisit.alias("revisit"), "owner")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = _filesystem(folder)
        fs.create_dir(base, recursive=True)
        held: list[bytes] = []
        size = 0
        out = dictionary = name = None
        count = 0

        def start() -> None:
            nonlocal out, dictionary, name, count
            name = f"part-{uuid.uuid4().hex}.warc.zst"
            dictionary = dictionary_of(held)
            out, count = fs.open_output_stream(f"{base}/{name}", compression=None), 0
            head(dictionary)

        def head(d: zstandard.ZstdCompressionDict | None) -> None:
            nonlocal zip_
            write_archive(out, iter(()), d)
            zip_ = zstandard.ZstdCompressor(level=3, dict_data=d, write_content_size=True)

        def put() -> None:
            nonlocal count
            for r in held:
                out.write(zip_.compress(r))
            count += len(held)
            held.clear()

        def close() -> pa.RecordBatch:
            nonlocal out
            put()
            n = out.tell()
            out.close()
            out = None
            return pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}"]), pa.array([count], pa.int64()), pa.array([n], pa.int64())], ["path", "records", "bytes"])

        zip_ = None
        since = 0
        for batch in batches:
            for r in zip(*(common.column(batch, c).to_pylist() for c in ("page_id", "url", "html", "sha", "size", "revisit", "owner")), strict=True):
                page_id, url, html, sha, n_bytes, again, owner = r
                payload = b"" if again else html.encode()
                own = base64.b32encode(bytes.fromhex(sha)).decode()
                raw = record(page_id, url, payload, own, again, owner)
                if again:  # its HTTP header tells the payload's length
                    raw = _revisit(page_id, url, n_bytes, own, owner)
                held.append(raw)
                size += len(raw)
                since += len(raw)
                if out is None and (len(held) >= TRAIN_RECORDS or since >= TRAIN_BYTES):
                    start()
                if out is not None:
                    put()
                    if size >= FILE_BYTES:
                        yield close()
                        size = since = 0
        if held or out is not None:
            if out is None:
                start()
            yield close()

    return common.materialise(rows.mapInArrow(common.tidy(run), "path string, records long, bytes long"), "warc-files")


def _revisit(page_id: int | None, url: str | None, n_bytes: int, own: str, owner: int | None) -> bytes:
    class Sized(bytes):
        def __len__(self) -> int:
            return n_bytes

    return record(page_id, url, Sized(), own, True, owner)


def read(files: DataFrame, payloads: bool = False) -> DataFrame:
    """The records of the archives listed in `files` (path): page_id, payload_bytes, payload_digest, record_type, refers_to (and url, payload).

    Every record's version line, headers, lengths and digests are checked; a bad one raises WarcError with its file.
    """
    fields = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long" + ", url string, payload binary" * payloads
    names = [x.split()[0] for x in fields.split(", ")]
    kinds = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
    types = [kinds[x.split()[1]] for x in fields.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path in common.column(batch, "path").to_pylist():
                fs, at = _filesystem(path)
                rows: list[dict] = []
                size = 0
                with fs.open_input_stream(at, compression=None) as src:
                    try:
                        for raw in read_archive(src):
                            rows.append(parse(raw))
                            size += len(raw) * payloads
                            if len(rows) >= 4096 or size > 8 << 20:
                                yield _batch(rows, names, types)
                                rows, size = [], 0
                    except (WarcError, zstandard.ZstdError) as e:
                        raise WarcError(f"{path}: {e}") from e
                if rows:
                    yield _batch(rows, names, types)

    n = common.partitions(files.sparkSession)
    return files.select("path").repartition(n, "path").mapInArrow(common.tidy(run), fields)


def _batch(rows: list[dict], names: list[str], types: list[pa.DataType]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], t) for c, t in zip(names, types, strict=True)], names)


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(write(spark.read.parquet(f"{sf_dir}/pages.parquet")))


OP6_SQL = r"""
WITH p AS (
  SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS h FROM pages
), o AS (
  SELECT h, max(page_id) AS owner FROM p GROUP BY h
)
SELECT page_id, payload_bytes,
       array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substr(h, (1 + 5 * (i // 4))::BIGINT, 5))::BIGINT >> (15 - 5 * (i % 4))::BIGINT) & 31), 1)), '') AS payload_digest,
       CASE WHEN page_id = owner THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id = owner THEN NULL ELSE owner END AS refers_to
FROM p JOIN o USING (h)
"""
