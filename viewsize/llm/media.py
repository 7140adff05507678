"""Payloads as media members of archives, read back through a Spark data source.

Writing: each task streams its rows into one archive (a ZIP of stored members) in the shared folder; a member is an 8-bit
greyscale PNG, 64 samples a row, whose samples are the payload. A manifest row for each archive names the attempt that
was committed, so what a lost task left behind is never read.

Reading: the data source ``payload_archive`` plans byte ranges of the archives from their sizes alone; the task of a range reads the
central directory at the archive's end, keeps the members whose header starts inside the range, and fetches each by its offset. A member
that fails its checksum or its read is fetched again on a new handle, without disturbing the others, and is reported with its error
once its attempts are used up. Batches of payloads leave through Arrow.
"""

from __future__ import annotations

import io
import struct
import uuid
import zipfile
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..session import ship
from .common import scratch, settle

ROW = 64
# Fixed values of the PNG format: signature, header fields after width and height (8-bit greyscale, deflate, no interlace), end chunk.
_SIGNATURE = b"\x89PNG\r\n\x1a\n"
_DEPTH = b"\x08\x00\x00\x00\x00"
_BATCH_BYTES = 8 << 20


def pad(raw: bytes) -> bytes:
    """The bytes with zeros appended up to a positive multiple of 64."""
    return raw + b"\0" * (max(ROW, -(-len(raw) // ROW) * ROW) - len(raw))


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def encode(payload: bytes) -> bytes:
    """A payload of a positive multiple of 64 bytes as PNG."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, ROW)
    lines = np.zeros((len(rows), ROW + 1), np.uint8)  # the first byte of a line is its filter: none
    lines[:, 1:] = rows
    return _SIGNATURE + _chunk(b"IHDR", struct.pack(">II", ROW, len(rows)) + _DEPTH) + _chunk(b"IDAT", zlib.compress(lines.tobytes(), 5)) + _chunk(b"IEND", b"")


def decode(media: bytes) -> bytes:
    """The samples of such a PNG; anything else raises ValueError."""
    if media[:8] != _SIGNATURE:
        raise ValueError("not a PNG")
    at, data, height = 8, [], 0
    while at + 12 <= len(media):
        (n,), kind = struct.unpack_from(">I", media, at), media[at + 4 : at + 8]
        body = media[at + 8 : at + 8 + n]
        if len(body) < n or struct.unpack_from(">I", media, at + 8 + n)[0] != zlib.crc32(kind + body):
            raise ValueError("damaged chunk")
        if kind == b"IHDR":
            width, height = struct.unpack_from(">II", body)
            if width != ROW or body[8:] != _DEPTH:
                raise ValueError("not 8-bit greyscale of 64 samples a row")
        elif kind == b"IDAT":
            data.append(body)
        at += 12 + n
    lines = np.frombuffer(zlib.decompress(b"".join(data)), np.uint8)
    if not height or len(lines) != height * (ROW + 1):
        raise ValueError("wrong number of samples")
    lines = lines.reshape(height, ROW + 1)
    if lines[:, 0].any():
        raise ValueError("filtered lines")
    return lines[:, 1:].tobytes()


def feature(payload: bytes) -> str:
    """What a payload sounds like, of its samples alone: mean, deviation and entropy in thousandths, zero share in thousandths, and 8 band counts."""
    c = np.bincount(np.frombuffer(payload, np.uint8), minlength=256).astype(np.int64)
    n = len(payload)
    v = np.arange(256)
    mean = int((c * v).sum()) / n
    var = int((c * v * v).sum()) / n - mean * mean
    p = c[c > 0] / n
    entropy = float(-(p * np.log2(p)).sum())
    bands = ",".join(map(str, c.reshape(8, 32).sum(axis=1).tolist()))
    return f"mean={round(mean * 1000)};dev={round(max(0.0, var) ** 0.5 * 1000)};entropy={round(entropy * 1000)};zero={round(1000 * int(c[0]) / n)};bands={bands}"


def _fs(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


class _Counting(io.RawIOBase):
    """A forward-only sink that ZipFile can write to (it never seeks in one)."""

    def __init__(self, out):
        self.out, self.at = out, 0

    def writable(self) -> bool:
        return True

    def write(self, data) -> int:
        self.out.write(data)
        self.at += len(data)
        return len(data)

    def tell(self) -> int:
        return self.at

    def flush(self) -> None:
        pass


def _writer(folder: str):
    def run(batches):
        fs, base = _fs(folder)
        fs.create_dir(base, recursive=True)
        name, members = f"{uuid.uuid4().hex}.zip", 0
        with fs.open_output_stream(f"{base}/{name}") as out:
            sink = _Counting(out)
            with zipfile.ZipFile(sink, "w", zipfile.ZIP_STORED, allowZip64=True) as z:
                for batch in batches:
                    for doc_id, text in zip(batch.column(0), batch.column(1)):
                        raw = (text.as_py() or "").encode("utf-8", "surrogatepass")
                        own = doc_id.as_py()
                        info = zipfile.ZipInfo(f"{members}.{'' if own is None else own}.{len(raw)}")
                        z.writestr(info, encode(pad(raw)))
                        members += 1
        yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([members], pa.int64()), pa.array([sink.at], pa.int64())], names=["archive", "members", "bytes"])

    return run


def write_archives(docs: DataFrame, folder: str) -> DataFrame:
    """docs (doc_id, text) into archives under folder; gives the manifest (archive, members, bytes) of the committed ones."""
    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return settle(rows.mapInArrow(_writer(folder), "archive string, members long, bytes long"), "manifest")


@dataclass
class ByteRange(InputPartition):
    archive: str
    start: int
    end: int


class _Reading(io.RawIOBase):
    """A file of any file system as ZipFile expects one: a seek before the start is an OSError."""

    def __init__(self, handle):
        self.handle = handle

    def readable(self) -> bool:
        return True

    def seekable(self) -> bool:
        return True

    def read(self, n: int = -1) -> bytes:
        return self.handle.read(None if n is None or n < 0 else n)

    def tell(self) -> int:
        return self.handle.tell()

    def seek(self, at: int, whence: int = 0) -> int:
        if (at if whence == 0 else at + (self.handle.tell() if whence == 1 else self.handle.size())) < 0:
            raise OSError("before the start")
        return self.handle.seek(at, whence)


def _members(handle, start: int, end: int) -> list[tuple[str, int, int, int]]:
    """(name, offset, stored bytes, crc) of the members whose header starts in [start, end), from the central directory."""
    with zipfile.ZipFile(_Reading(handle)) as z:
        return [(i.filename, i.header_offset, i.compress_size, i.CRC) for i in z.infolist() if start <= i.header_offset < end]


def fetch(fs: pafs.FileSystem, path: str, offset: int, stored: int, crc: int, handle=None) -> bytes:
    """One stored member by its offset; ValueError if it isn't what the directory says."""
    own = handle or fs.open_input_file(path)
    try:
        head = own.read_at(30, offset)
        if head[:4] != b"PK\x03\x04":
            raise ValueError("no member header")
        n, extra = struct.unpack_from("<HH", head, 26)
        body = own.read_at(stored, offset + 30 + n + extra)
        if len(body) != stored or zlib.crc32(body) != crc:
            raise ValueError("checksum")
        return body
    finally:
        if handle is None:
            own.close()


class ArchiveReader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder, self.attempts = options["path"], int(options.get("attempts", "3"))
        self.split = int(options.get("splitbytes", str(64 << 20)))
        self.archives = options.get("archives")

    def partitions(self) -> list[ByteRange]:
        fs, base = _fs(self.folder)
        if self.archives is not None:
            found = [(n, int(s)) for n, s in (x.rsplit(":", 1) for x in self.archives.split(",") if x)]
        else:
            infos = fs.get_file_info(pafs.FileSelector(base, allow_not_found=True))
            found = sorted((i.base_name, i.size) for i in infos if i.is_file and i.base_name.endswith(".zip"))
        return [ByteRange(n, at, min(size, at + self.split)) for n, size in found for at in range(0, size, self.split)] or [ByteRange("", 0, 0)]

    def read(self, part: ByteRange) -> Iterator[pa.RecordBatch]:
        if not part.archive:
            return
        fs, base = _fs(self.folder)
        path = f"{base}/{part.archive}"
        rows, held = [], 0
        with fs.open_input_file(path) as handle:
            for name, offset, stored, crc in _members(handle, part.start, part.end):
                media, error = None, None
                for attempt in range(self.attempts):
                    try:
                        media, error = fetch(fs, path, offset, stored, crc, None if attempt else handle), None
                        break
                    except (OSError, ValueError) as e:
                        error = f"{type(e).__name__}: {e}"
                rows.append((part.archive, name, offset, media, error))
                held += stored
                if held >= _BATCH_BYTES:
                    yield _batch(rows)
                    rows, held = [], 0
        if rows:
            yield _batch(rows)


_SCHEMA = pa.schema([("archive", pa.string()), ("member", pa.string()), ("offset", pa.int64()), ("media", pa.binary()), ("error", pa.string())])


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), _SCHEMA)], schema=_SCHEMA)


class PayloadArchive(DataSource):
    """format("payload_archive"), options: path (folder), archives (name:bytes, comma-separated; default: all of the folder), splitbytes, attempts."""

    @classmethod
    def name(cls) -> str:
        return "payload_archive"

    def schema(self) -> str:
        return "archive string, member string, offset long, media binary, error string"

    def reader(self, schema) -> DataSourceReader:
        return ArchiveReader(self.options)


def read_archives(spark: SparkSession, folder: str, manifest: DataFrame | None = None, **options: str) -> DataFrame:
    """The members of the archives of a folder, or of those in a manifest (one short row for each writing task is gathered)."""
    ship(spark)
    spark.dataSource.register(PayloadArchive)
    reader = spark.read.format("payload_archive").options(**options)
    if manifest is not None:
        reader = reader.option("archives", ",".join(f"{r['archive']}:{r['bytes']}" for r in manifest.select("archive", "bytes").collect()))
    return reader.load(folder)


def _describe(batches):
    import hashlib

    for batch in batches:
        out = []
        for member, media in zip(batch.column(0), batch.column(1)):
            _, own, n = member.as_py().split(".")
            media = media.as_py()
            payload = decode(media)
            out.append((
                int(own) if own else None, int(n), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-ROW:]), len(media), hashlib.sha256(media).hexdigest(), feature(payload)
            ))
        cols = list(zip(*out)) or [()] * 8
        kinds = [pa.int64()] * 3 + [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
        yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds)], names=names)


def media_features(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) -> one row per document, from the stored bytes as read back: (doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32,
    media_bytes, media_sha256, feature). Null texts count as empty: 64 zero bytes. Equal texts get equal values; repeated rows and null ids pass
    through; no rows give no rows; other columns are ignored. A member that stays unreadable fails the query rather than go missing."""
    folder = f"{scratch(docs.sparkSession)}/archives"
    manifest = write_archives(docs, folder)
    found = read_archives(docs.sparkSession, folder, manifest)
    sound = F.when(F.col("error").isNull(), F.col("media")).otherwise(F.raise_error(F.concat(F.lit("unreadable member "), "archive", F.lit("/"), "member", F.lit(": "), "error")))
    return found.select("member", sound.alias("media")).mapInArrow(
        _describe, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    )
