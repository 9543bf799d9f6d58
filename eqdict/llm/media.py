"""Media columns: content-addressed payloads in tar shards.

A text's UTF-8 bytes, filled with zero bytes to a positive multiple of 64, are the pixels of an 8-bit grey image 64 wide, stored
losslessly as PNG. Each task writes the payloads it meets, once each, to tar shards in a folder that all executors share; rows carry
digest, shard, offset and length. Of the places that hold one digest the smallest is the one that counts. Header-only range reads
fill the metadata columns, and reads of the whole range give checksums and features; both walk a shard front to back.

A shard counts only through the rows that Spark committed: a lost or repeated task leaves at most shards that no row names.
"""

from __future__ import annotations

import hashlib
import struct
import tarfile
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqdict.llm.common import parts_of, staged, workdir

WIDTH = 64
SHARD_BYTES = 256 << 20
HEADER_BYTES = 33  # PNG's signature and its IHDR chunk
_SIGNATURE = b"\x89PNG\r\n\x1a\n"
PLACES = "doc_id long, n_bytes long, digest binary, shard string, at long, media_bytes long"
FACTS = "digest binary, shard string, at long, width long, height long, bits long, payload_bytes long, tail_crc32 long, media_bytes long, media_digest binary, feature string"
HEADERS = "digest binary, shard string, at long, width long, height long, bits long, media_bytes long"


def padded(data: bytes) -> bytes:
    return data + bytes(-len(data) % WIDTH if data else WIDTH)


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def to_png(payload: bytes, level: int = 1) -> bytes:
    rows = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    lines = np.zeros((len(rows), WIDTH + 1), np.uint8)  # each line starts with its filter type, none
    lines[:, 1:] = rows
    return _SIGNATURE + _chunk(b"IHDR", struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0)) + _chunk(b"IDAT", zlib.compress(lines.tobytes(), level)) + _chunk(b"IEND", b"")


def png_header(data: bytes) -> tuple[int, int, int]:
    """(width, height, bits) from the first HEADER_BYTES bytes."""
    if data[:8] != _SIGNATURE or data[12:16] != b"IHDR" or struct.unpack(">I", data[29:33])[0] != zlib.crc32(data[12:29]):
        raise ValueError("not a PNG header")
    return struct.unpack(">IIB", data[16:25])


def from_png(data: bytes) -> bytes:
    """The pixels of an image that to_png wrote."""
    width, height, _ = png_header(data)
    at, body = HEADER_BYTES, []
    while (kind := data[at + 4 : at + 8]) != b"IEND":
        size = struct.unpack(">I", data[at : at + 4])[0]
        if kind == b"IDAT":
            body.append(data[at + 8 : at + 8 + size])
        at += 12 + size
    lines = np.frombuffer(zlib.decompress(b"".join(body)), np.uint8).reshape(height, width + 1)
    if lines[:, 0].any():
        raise ValueError("filtered lines")
    return lines[:, 1:].tobytes()


def feature(payload: bytes) -> str:
    """Mean, deviation and entropy of the samples, and the share of the most frequent one."""
    share = np.bincount(np.frombuffer(payload, np.uint8), minlength=256) / len(payload)
    mean = float(share @ np.arange(256))
    spread = float(np.sqrt(share @ (np.arange(256) - mean) ** 2))
    seen = share[share > 0]
    return f"mean={mean:.4f};sd={spread:.4f};entropy={abs(float(-(seen * np.log2(seen)).sum())):.4f};top={int(share.argmax())}:{float(share.max()):.4f}"


class _Shard:
    """A tar file that is written front to back."""

    def __init__(self, folder: str):
        self.name = f"{uuid.uuid4().hex}.tar"
        fs, path = pafs.FileSystem.from_uri(folder)
        fs.create_dir(path, recursive=True)
        self.out, self.size = fs.open_output_stream(f"{path}/{self.name}"), 0

    def add(self, name: str, data: bytes) -> int:
        info = tarfile.TarInfo(name)
        info.size = len(data)
        head = info.tobuf(tarfile.PAX_FORMAT)
        at = self.size + len(head)
        self.out.write(head + data + bytes(-len(data) % 512))
        self.size = at + len(data) + -len(data) % 512
        return at

    def close(self) -> None:
        self.out.write(bytes(1024))
        self.out.close()


def uri(folder: str) -> str:
    return folder if "://" in folder or folder.startswith("file:") else f"file://{folder}"


def stored(docs: DataFrame, folder: str, shard_bytes: int = SHARD_BYTES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For every row its place: doc_id, n_bytes, digest (of the payload), shard, at, media_bytes. Written as a table beside the shards."""
    shards = f"{uri(folder)}/shards"

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, seen = None, {}
        for b in batches:
            out = []
            for d, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                data = (t.as_py() or "").encode()
                payload = padded(data)
                digest = hashlib.sha256(payload).digest()
                if digest not in seen:
                    if shard is None or shard.size >= shard_bytes:
                        if shard:
                            shard.close()
                        shard, seen = _Shard(shards), {}
                    image = to_png(payload)
                    seen[digest] = (shard.name, shard.add(f"{digest.hex()}.png", image), len(image))
                out.append((d, len(data), digest, *seen[digest]))
            cols = list(zip(*out, strict=True)) or [()] * 6
            kinds = (pa.int64(), pa.int64(), pa.binary(), pa.string(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "n_bytes", "digest", "shard", "at", "media_bytes"])
        if shard:
            shard.close()

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text"))
    return staged(rows.mapInArrow(write, PLACES), f"{folder}/places")


def places(rows: DataFrame) -> DataFrame:
    """The one place of each digest: digest, shard, at, media_bytes. Rows of one shard come together, in its order.

    The rows are small but stand for whole shards, so their number of tasks is not left to adaptive coalescing.
    """
    tasks = max(parts_of(rows.sparkSession), rows.agg(F.count_distinct("shard")).first()[0])
    one = rows.groupBy("digest").agg(F.min(F.struct("shard", "at", "media_bytes")).alias("p")).select("digest", "p.*")
    return one.repartition(tasks, "shard").sortWithinPartitions("shard", "at")


def _ranges(folder: str, batches: Iterator[pa.RecordBatch], whole: bool) -> Iterator[list[tuple]]:
    """Lists of (digest, shard, at, size, bytes read, further columns)."""
    fs, path = pafs.FileSystem.from_uri(f"{uri(folder)}/shards")
    name = file = None
    for b in batches:
        out, held = [], 0
        for digest, shard, at, size, *more in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if shard != name:
                if file:
                    file.close()
                name, file = shard, fs.open_input_file(f"{path}/{shard}")
            out.append((digest, shard, at, size, file.read_at(size if whole else HEADER_BYTES, at), *more))
            held += len(out[-1][4])
            if held > 32 << 20:
                yield out
                out, held = [], 0
        yield out
    if file:
        file.close()


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = [(n, {"string": pa.string(), "binary": pa.binary()}.get(k, pa.int64())) for n, k in (c.split() for c in schema.split(", "))]
    cols = list(zip(*rows, strict=True)) or [()] * len(kinds)
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, (_, k) in zip(cols, kinds, strict=True)], [n for n, _ in kinds])


def headers(at: DataFrame, folder: str) -> DataFrame:
    """Metadata columns of each place, from HEADER_BYTES bytes of each."""

    def read(batches):
        for part in _ranges(folder, batches, whole=False):
            yield _batch([(d, shard, at, *png_header(data), size) for d, shard, at, size, data in part], HEADERS)

    return at.select("digest", "shard", "at", "media_bytes").mapInArrow(read, HEADERS)


def facts(at: DataFrame, folder: str) -> DataFrame:
    """Metadata columns from `headers`, then checksums and features from the stored bytes. A payload that does not have its digest
    or its header raises an error."""

    def read(batches):
        for part in _ranges(folder, batches, whole=True):
            out = []
            for digest, shard, place, size, data, *head in part:
                payload = from_png(data)
                if len(data) != size or hashlib.sha256(payload).digest() != digest or png_header(data) != tuple(head):
                    raise ValueError(f"payload {digest.hex()} is damaged")
                out.append((digest, shard, place, *head, len(payload), zlib.crc32(payload[-64:]), len(data), hashlib.sha256(data).digest(), feature(payload)))
            yield _batch(out, FACTS)

    return headers(at, folder).select("digest", "shard", "at", "media_bytes", "width", "height", "bits").mapInArrow(read, FACTS)


def media_columns(docs: DataFrame, folder: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For every row: doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature, width, height, bits, shard, at.

    Null counts as empty, which is stored as 64 zero bytes. Equal texts have equal values and one place. Repeated rows and null
    identifiers give a row each. Other columns are ignored, whatever their names. An empty table gives no rows.
    """
    folder = folder or workdir(docs.sparkSession, "media")
    rows = stored(docs, folder, id_col=id_col, text_col=text_col)
    out = rows.select("doc_id", "n_bytes", "digest").join(facts(places(rows), folder), "digest")
    hexed = lambda c: F.lower(F.hex(c))
    return out.select("doc_id", "n_bytes", "payload_bytes", hexed("digest").alias("payload_sha256"), "tail_crc32", "media_bytes", hexed("media_digest").alias("media_sha256"), "feature", "width", "height", "bits", "shard", "at")
