"""Media columns: Netpbm and BMP to numpy, area resizing, NPY tiles, difference hashes.

``encode_payloads`` stores bytes losslessly as an image, ``read_media`` reads
stored images of any supported kind back.  Resizing takes the mean over the
exact area of each target cell, from an integral image that is read at
fractional edges (a box filter is piecewise linear between its samples).
"""

from __future__ import annotations

import hashlib
import io
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import blocks

#: Bytes in a row of a stored payload, and what it is padded to.
ROW = 64


def decode(data: bytes) -> np.ndarray:
    """Array (height, width) or (height, width, channels) of a PBM, PGM, PPM (plain or raw) or an uncompressed BMP."""
    if data[:2] == b"BM":
        return _bmp(data)
    if len(data) > 2 and data[:1] == b"P" and data[1:2] in b"123456":
        return _netpbm(data)
    raise ValueError("neither Netpbm nor BMP")


def _netpbm(data: bytes) -> np.ndarray:
    kind, at, header = int(data[1:2]), 2, []
    need = 2 if kind in (1, 4) else 3
    while len(header) < need:
        while data[at : at + 1].isspace():
            at += 1
        if data[at : at + 1] == b"#":
            at = data.index(b"\n", at)
            continue
        end = at
        while data[end : end + 1].isdigit():
            end += 1
        if end == at:
            raise ValueError("broken Netpbm header")
        header.append(int(data[at:end]))
        at = end
    width, height = header[:2]
    top = header[2] if need == 3 else 1
    channels = 3 if kind in (3, 6) else 1
    n = width * height * channels
    if kind <= 3:
        body = b"\n".join(line.split(b"#")[0] for line in data[at:].split(b"\n"))
        flat = np.array([int(x) for x in (body.split() if kind > 1 else list("".join(body.decode().split())))], dtype=np.int64)[:n]
    else:
        at += 1  # the one white space after the header
        if kind == 4:
            row = (width + 7) // 8
            bits = np.unpackbits(np.frombuffer(data, np.uint8, row * height, at).reshape(height, row), axis=1)
            flat = bits[:, :width].reshape(-1)
        else:
            flat = np.frombuffer(data, np.uint8 if top < 256 else ">u2", n, at)
    if flat.size != n:
        raise ValueError("too few samples")
    if need == 2:
        flat = 1 - flat  # in a bitmap 1 is black
    out = flat.astype(np.uint8 if top < 256 else np.uint16)
    return out.reshape((height, width, 3) if channels == 3 else (height, width))


def _bmp(data: bytes) -> np.ndarray:
    start, = struct.unpack_from("<I", data, 10)
    header, width, height, _, bits, packed = struct.unpack_from("<IiiHHI", data, 14)
    if packed or bits not in (8, 24, 32):
        raise ValueError("only uncompressed BMP of 8, 24 or 32 bits")
    stride = (width * bits // 8 + 3) // 4 * 4
    rows = np.frombuffer(data, np.uint8, stride * abs(height), start).reshape(abs(height), stride)
    rows = rows[:, : width * bits // 8] if height < 0 else rows[::-1, : width * bits // 8]
    if bits == 8:
        colours, = struct.unpack_from("<I", data, 46)
        palette = np.frombuffer(data, np.uint8, 4 * (colours or 256), 14 + header).reshape(-1, 4)
        out = palette[rows][:, :, 2::-1]
        return out[:, :, 0] if (out == out[:, :, :1]).all() else out
    return rows.reshape(abs(height), width, bits // 8)[:, :, 2::-1]


def encode_pgm(samples: np.ndarray) -> bytes:
    height, width = samples.shape
    return b"P5\n%d %d\n255\n" % (width, height) + samples.astype(np.uint8).tobytes()


def encode_bmp(samples: np.ndarray) -> bytes:
    """8-bit grey BMP, top row first."""
    height, width = samples.shape
    stride = (width + 3) // 4 * 4
    rows = np.zeros((height, stride), np.uint8)
    rows[:, :width] = samples
    palette = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 4, axis=1)
    palette[:, 3] = 0
    start = 54 + palette.size
    head = struct.pack("<2sIHHI", b"BM", start + rows.size, 0, 0, start)
    head += struct.pack("<IiiHHIIiiII", 40, width, -height, 1, 8, 0, rows.size, 2835, 2835, 256, 0)
    return head + palette.tobytes() + rows.tobytes()


def area_resize(image: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of the image over each cell of a height x width grid."""
    if not image.size:
        return np.zeros((height, width, *image.shape[2:]))
    sums = np.zeros((image.shape[0] + 1, image.shape[1] + 1, *image.shape[2:]))
    np.cumsum(image, axis=0, out=sums[1:, 1:], dtype=np.float64)
    np.cumsum(sums[1:, 1:], axis=1, out=sums[1:, 1:])

    def at(table: np.ndarray, n: int) -> np.ndarray:
        edges = np.arange(n + 1) * ((table.shape[0] - 1) / n)
        low = np.minimum(edges.astype(np.int64), table.shape[0] - 2)
        part = (edges - low).reshape(-1, *[1] * (table.ndim - 1))
        return table[low] * (1 - part) + table[low + 1] * part

    boxes = at(np.swapaxes(at(sums, height), 0, 1), width)
    boxes = np.swapaxes(boxes, 0, 1)
    cells = np.diff(np.diff(boxes, axis=0), axis=1)
    return cells * (height * width / (image.shape[0] * image.shape[1]))


def grey(image: np.ndarray) -> np.ndarray:
    return image if image.ndim == 2 else image[:, :, :3].astype(np.float64).mean(axis=2)


def difference_hash(image: np.ndarray, size: int = 8) -> str:
    """Hex of size * size bits: is a cell darker than its right neighbour, on a size x (size + 1) grid."""
    cells = np.round(area_resize(grey(image), size, size + 1), 6)
    return np.packbits(cells[:, :-1] < cells[:, 1:]).tobytes().hex()


def npy_tile(image: np.ndarray, size: int = 32) -> bytes:
    """NPY file of the image at size x size, 8-bit."""
    out = io.BytesIO()
    np.save(out, np.clip(np.rint(area_resize(image, size, size)), 0, 255).astype(np.uint8))
    return out.getvalue()


def encode_payloads(docs: DataFrame, fmt: str = "pgm") -> DataFrame:
    """(doc_id, n_bytes, media): UTF-8 of the text, zero-padded to a positive multiple of 64, as an image 64 wide.

    fmt is pgm, bmp or mixed: images of an odd number of rows as PGM, of an even
    one as BMP.  Null is stored like the empty text.  The padding isn't part of
    n_bytes.
    """
    encode = {"pgm": encode_pgm, "bmp": encode_bmp, "mixed": lambda image: (encode_pgm if image.shape[0] % 2 else encode_bmp)(image)}[fmt]

    def stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            sizes, media = [], []
            for t in batch.column("text").to_pylist():
                t = t or b""
                sizes.append(len(t))
                padded = t.ljust(max(1, -(-len(t) // ROW)) * ROW, b"\0")
                media.append(encode(np.frombuffer(padded, np.uint8).reshape(-1, ROW)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("binary").alias("text")).mapInArrow(stored, f"doc_id {kind}, n_bytes long, media binary")


def read_media(media: DataFrame, tile: int = 32) -> DataFrame:
    """Columns of ``media`` (doc_id, n_bytes, media) with what its stored bytes decode to.

    Adds height, width, payload_bytes, payload_sha256, tail_crc32, media_bytes,
    media_sha256, feature (difference hash) and tile (NPY file).  Bytes that
    don't decode, or null, give nulls in what needs the image.
    """

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "media"):
            rows = []
            for data in batch.column("media").to_pylist():
                try:
                    image = decode(data)
                except (ValueError, struct.error, TypeError, IndexError):
                    rows.append((None,) * 5 + ((None, None) if data is None else (len(data), hashlib.sha256(data).hexdigest())) + (None, None))
                    continue
                payload = np.ascontiguousarray(image).tobytes()
                rows.append((
                    image.shape[0], image.shape[1], len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-ROW:]),
                    len(data), hashlib.sha256(data).hexdigest(), difference_hash(image), npy_tile(image, tile) if tile else None,
                ))
            cols = list(zip(*rows, strict=True))
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), *map(pa.array, cols, kinds)], names)

    names = ["doc_id", "n_bytes", "height", "width", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "tile"]
    kind = media.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, n_bytes long, height int, width int, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, tile binary"
    return media.select("doc_id", "n_bytes", "media").mapInArrow(read, schema)


def tile_hash(tile: bytes) -> str:
    """Difference hash of an NPY tile as it is read back."""
    return difference_hash(np.load(io.BytesIO(tile)))


def document_media(docs: DataFrame, tile: int = 32, fmt: str = "mixed") -> DataFrame:
    """The digest row of each document, by way of its stored image and the NPY tile written from it.

    feature joins the difference hash of the image and that of its tile.
    """

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tiles = batch.column("tile").to_pylist()
            features = [f"{f}-{tile_hash(t)}" for f, t in zip(batch.column("feature").to_pylist(), tiles, strict=True)]
            digests = [hashlib.sha256(t).hexdigest() for t in tiles]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names[:-2]), pa.array(features, pa.string()), pa.array(digests, pa.string())], names)

    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "tile_sha256"]
    kind = docs.schema["doc_id"].dataType.simpleString()
    read = read_media(encode_payloads(docs, fmt), tile).select(*names[:-1], "tile")
    return read.mapInArrow(digest, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, tile_sha256 string")


def write_tiles(media: DataFrame, path: str, tile: int = 32) -> None:
    """Writes (doc_id, height, width, feature, tile) of stored images as a Parquet table whose tile column holds NPY files; images that don't decode are left out."""
    read_media(media, tile).where("tile is not null").select("doc_id", "height", "width", "feature", "tile").write.mode("overwrite").parquet(path)


def read_tiles(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, height, width, feature, samples): the tiles' samples as flat arrays."""

    def load(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            samples = [np.load(io.BytesIO(t)).ravel() for t in batch.column("tile").to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(samples, pa.list_(pa.int32()))], ["doc_id", "height", "width", "feature", "samples"])

    rows = spark.read.parquet(path).select("doc_id", "height", "width", "feature", "tile")
    kind = rows.schema["doc_id"].dataType.simpleString()
    return rows.mapInArrow(load, f"doc_id {kind}, height int, width int, feature string, samples array<int>")
