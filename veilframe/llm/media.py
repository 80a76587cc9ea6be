"""Media columns: Netpbm and BMP bytes decoded to numpy arrays, area-resized, written as NPY tiles with difference hashes.

Null or empty media decode to nothing: tile, hash and shape are null. Bytes that are no whole image of a
known kind raise no error in a column operator; their `error` column says why. Equal bytes give equal rows.
"""

from __future__ import annotations

import hashlib
import io
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

WIDTH = 64


class MediaError(ValueError):
    """The bytes are no image that this module reads."""


_FIELD = re.compile(rb"(?:\s|#[^\n\r]*[\n\r]?)*(\d+)")


def _fields(data: bytes, n: int) -> tuple[list[int], int]:
    at, out = 2, []
    for _ in range(n):
        m = _FIELD.match(data, at)
        if not m:
            raise MediaError("header ends early")
        out.append(int(m[1]))
        at = m.end()
    return out, at


def decode_netpbm(data: bytes) -> np.ndarray:
    """P1 to P6 as (height, width) or (height, width, 3), uint8 or uint16. In bitmaps 1 is black and becomes 0."""
    kind = data[1] - 48 if len(data) > 2 and data[:1] == b"P" else 0
    if not 1 <= kind <= 6:
        raise MediaError("no Netpbm magic number")
    head, at = _fields(data, 2 if kind in (1, 4) else 3)
    width, height = head[:2]
    top = head[2] if len(head) > 2 else 1
    if not (width and height and 0 < top < 65536):
        raise MediaError("empty or wrong size")
    depth = 3 if kind in (3, 6) else 1
    n = width * height * depth
    if kind == 4:
        row = (width + 7) // 8
        raw = np.frombuffer(data, np.uint8, count=_need(data, at + 1, row * height), offset=at + 1)
        values = 1 - np.unpackbits(raw.reshape(height, row), axis=1)[:, :width]
    elif kind > 4:
        size = 2 if top > 255 else 1
        _need(data, at + 1, n * size)
        values = np.frombuffer(data, ">u2" if size == 2 else np.uint8, count=n, offset=at + 1)
    else:
        body = re.sub(rb"#[^\n\r]*", b"", data[at:])
        items = re.findall(rb"[01]", body) if kind == 1 else body.split()
        if len(items) < n:
            raise MediaError("too few samples")
        values = np.array(items[:n], dtype="S5").astype(np.int64)
        values = 1 - values if kind == 1 else values
    values = np.asarray(values).reshape((height, width, 3) if depth == 3 else (height, width))
    if kind in (1, 4):
        values = values * 255
    return values.astype(np.uint16 if top > 255 else np.uint8)


def _need(data: bytes, at: int, n: int) -> int:
    if len(data) < at + n:
        raise MediaError("too few bytes")
    return n


def encode_pgm(samples: np.ndarray) -> bytes:
    height, width = samples.shape
    return b"P5\n%d %d\n255\n" % (width, height) + samples.astype(np.uint8).tobytes()


def encode_ppm(samples: np.ndarray) -> bytes:
    height, width, _ = samples.shape
    return b"P6\n%d %d\n255\n" % (width, height) + samples.astype(np.uint8).tobytes()


def encode_bmp(samples: np.ndarray) -> bytes:
    """8-bit grey (with a grey palette) or 24-bit colour, rows bottom up and padded to four bytes."""
    height, width = samples.shape[:2]
    grey = samples.ndim == 2
    body = samples if grey else samples[:, :, ::-1].reshape(height, -1)
    body = np.pad(body, ((0, 0), (0, -body.shape[1] % 4)))[::-1].astype(np.uint8).tobytes()
    colours = b"".join(bytes((i, i, i, 0)) for i in range(256)) if grey else b""
    start = 54 + len(colours)
    return b"BM" + struct.pack("<IHHI", start + len(body), 0, 0, start) + struct.pack("<IiiHHIIiiII", 40, width, height, 1, 8 if grey else 24, 0, len(body), 2835, 2835, 256 if grey else 0, 0) + colours + body


def decode_bmp(data: bytes) -> np.ndarray:
    """Uncompressed 1, 4, 8, 24 or 32 bits; a palette of greys gives (height, width), all else (height, width, 3)."""
    if len(data) < 54 or data[:2] != b"BM":
        raise MediaError("no BMP header")
    start, head, width, height, _, bits, packed = struct.unpack_from("<IIiiHHI", data, 10)
    if packed not in (0, 3) or bits not in (1, 4, 8, 24, 32) or width <= 0 or not height:
        raise MediaError("kind of BMP not read")
    rows, stride = abs(height), (width * bits + 31) // 32 * 4
    _need(data, start, rows * stride)
    raw = np.frombuffer(data, np.uint8, count=rows * stride, offset=start).reshape(rows, stride)
    raw = raw[::-1] if height > 0 else raw
    if bits >= 24:
        return raw[:, : width * bits // 8].reshape(rows, width, bits // 8)[:, :, 2::-1].copy()
    if bits == 8:
        index = raw[:, :width]
    elif bits == 4:
        index = np.stack([raw >> 4, raw & 15], axis=2).reshape(rows, -1)[:, :width]
    else:
        index = np.unpackbits(raw, axis=1)[:, :width]
    used = struct.unpack_from("<I", data, 46)[0] or 1 << bits
    _need(data, 14 + head, 4 * used)
    colours = np.frombuffer(data, np.uint8, count=4 * used, offset=14 + head).reshape(used, 4)[:, 2::-1]
    if index.size and int(index.max()) >= used:
        raise MediaError("colour outside the palette")
    out = colours[index]
    return out[:, :, 0].copy() if (colours == colours[:, :1]).all() else out


def decode(data: bytes) -> np.ndarray:
    return decode_bmp(data) if data[:2] == b"BM" else decode_netpbm(data)


def area_resize(image: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean over each target cell's exact area, cells cutting through pixels included, from an integral image."""
    image = np.asarray(image, dtype=np.float64)
    if image.ndim == 3:
        return np.stack([area_resize(image[:, :, c], height, width) for c in range(image.shape[2])], axis=2)
    total = np.zeros((image.shape[0] + 1, image.shape[1] + 1))
    np.cumsum(np.cumsum(image, axis=0), axis=1, out=total[1:, 1:])

    def at(lines: np.ndarray, cuts: int) -> np.ndarray:
        place = np.arange(cuts + 1) * (len(lines) - 1) / cuts
        low = np.minimum(place.astype(int), len(lines) - 2)
        part = (place - low)[:, None]
        return lines[low] * (1 - part) + lines[low + 1] * part

    cells = np.diff(np.diff(at(at(total, height).T, width).T, axis=0), axis=1)
    return cells * (height * width) / (image.shape[0] * image.shape[1])


def to_grey(image: np.ndarray) -> np.ndarray:
    return image if image.ndim == 2 else image.astype(np.float64) @ np.array([0.299, 0.587, 0.114])


def difference_hash(image: np.ndarray) -> int:
    """64 bits: in an 8 by 9 area-resized grey image, whether each cell is darker than its right neighbour."""
    small = np.round(area_resize(to_grey(image), 8, 9), 6)
    return int.from_bytes(np.packbits(small[:, :-1] < small[:, 1:]).tobytes(), "big")


def to_npy(array: np.ndarray) -> bytes:
    out = io.BytesIO()
    np.lib.format.write_array(out, np.ascontiguousarray(array), version=(1, 0), allow_pickle=False)
    return out.getvalue()


def tile_of(image: np.ndarray, side: int) -> np.ndarray:
    return np.clip(np.rint(area_resize(image, side, side)), 0, 65535 if image.dtype == np.uint16 else 255).astype(image.dtype)


def media_tiles(df: DataFrame, media: str = "media", keys: tuple[str, ...] = ("id",), side: int = 32) -> DataFrame:
    """keys, height, width, channels, tile (NPY bytes of side by side cells), dhash (16 hex digits), error."""
    kinds = [df.schema[k].simpleString().split(":", 1)[1] for k in keys]
    out = ", ".join([*(f"`{k}` {t}" for k, t in zip(keys, kinds, strict=True)), "height int, width int, channels int, tile binary, dhash string, error string"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for data in batch.column(len(keys)).to_pylist():
                if not data:
                    rows.append((None,) * 6)
                    continue
                try:
                    image = decode(data)
                except MediaError as e:
                    rows.append((None, None, None, None, None, str(e)))
                    continue
                rows.append((image.shape[0], image.shape[1], 1 if image.ndim == 2 else 3, to_npy(tile_of(image, side)), f"{difference_hash(image):016x}", None))
            made = [pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.string(), pa.string()))]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(keys))), *made], names=[*keys, "height", "width", "channels", "tile", "dhash", "error"])

    return df.select(*keys, F.col(media).cast("binary").alias("__media")).mapInArrow(work, out)


def payload_of(text: bytes) -> bytes:
    """The bytes followed by zeros up to a positive multiple of WIDTH."""
    return text + b"\0" * (-len(text) % WIDTH if text else WIDTH)


def store(payload: bytes, container: str = "pgm") -> bytes:
    """A grey image of WIDTH columns whose samples are the payload's bytes, in order."""
    samples = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    return encode_bmp(samples) if container == "bmp" else encode_pgm(samples)


TEXT_MEDIA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def text_media(docs: DataFrame, container: str = "pgm", side: int = 16) -> DataFrame:
    """Stores each text (null: empty) as an image, reads the image back, and describes what was read.

    feature: the difference hash and the head of the SHA-256 of the NPY tile. Repeated rows give repeated rows.
    """

    def describe(text: str | None) -> tuple:
        raw = (text or "").encode("utf-8", "surrogatepass")
        media = store(payload_of(raw), container)
        image = decode(media)
        back = image.tobytes()
        tile = to_npy(tile_of(image, side))
        return len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), f"{difference_hash(image):016x}-{hashlib.sha256(tile).hexdigest()[:16]}"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
        names = [x.split()[0] for x in TEXT_MEDIA.split(", ")]
        for batch in batches:
            rows = [describe(x.as_py()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds))], names=names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(work, TEXT_MEDIA)


def op9_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_media(table(spark, sf_dir, "documents"))


QUERIES = {"op9_media_columns": op9_media_columns}
ORACLES: dict[str, str] = {}
