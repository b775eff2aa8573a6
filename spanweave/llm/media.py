"""Media columns: Netpbm and BMP images as numpy arrays, area-resized by integral images, stored as NPY tiles
with difference hashes."""

from __future__ import annotations

import hashlib
import io
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.llm.shared import texts

#: Width in samples of the images that payloads are stored as, and the unit they are padded to.
ROW = 64


# ---- decoding
def decode(data: bytes) -> np.ndarray:
    """The samples of a Netpbm (P1 to P6) or BMP image, height x width (x 3), stretched to 0 to 255 (Netpbm images with a maximum above 255: to 65535). ValueError where it
    is neither, cut short, or holds values out of range."""
    if data[:2] == b"BM":
        return _bmp(data)
    if len(data) > 2 and data[:1] == b"P" and data[1:2] in b"123456":
        return _netpbm(data)
    raise ValueError("neither Netpbm nor BMP")


def _header(data: bytes, count: int) -> tuple[list[int], int]:
    """`count` numbers after the magic; comments run from # to the end of their line; one white space byte ends the last."""
    at, out = 2, []
    while len(out) < count:
        while at < len(data) and data[at : at + 1].isspace():
            at += 1
        if data[at : at + 1] == b"#":
            at = data.find(b"\n", at) + 1 or len(data)
            continue
        start = at
        while at < len(data) and data[at : at + 1].isdigit():
            at += 1
        if start == at:
            raise ValueError("a Netpbm header is cut short")
        out.append(int(data[start:at]))
    return out, at


def _netpbm(data: bytes) -> np.ndarray:
    kind = int(data[1:2])
    bitmap = kind in (1, 4)
    numbers, at = _header(data, 2 if bitmap else 3)
    width, height = numbers[:2]
    depth = 3 if kind in (3, 6) else 1
    most = 1 if bitmap else numbers[2]
    if not (width and height and 0 < most < 65536):
        raise ValueError("impossible Netpbm header")
    n = width * height * depth
    if n > 8 * len(data):
        raise ValueError("a Netpbm image is cut short")
    if kind <= 3:
        body = b"\n".join(line.split(b"#")[0] for line in data[at:].split(b"\n"))
        flat = np.frombuffer(body.translate(None, b" \t\r\n\v\f"), np.uint8)[:n].astype(np.int64) - 48 if bitmap else np.array(body.split()[:n], np.int64)
    elif kind == 4:
        step = (width + 7) // 8
        flat = np.unpackbits(np.frombuffer(data, np.uint8, step * height, at + 1).reshape(height, step), axis=1)[:, :width].ravel()
    else:
        flat = np.frombuffer(data, ">u2" if most > 255 else np.uint8, n, at + 1)
    if flat.size < n:
        raise ValueError("a Netpbm image is cut short")
    if n and not 0 <= int(flat.min()) <= int(flat.max()) <= most:
        raise ValueError("a Netpbm sample out of range")
    if bitmap:
        flat = (1 - flat.astype(np.uint8)) * np.uint8(255)  # 1 is black
    elif most not in (255, 65535):
        top = 255 if most < 255 else 65535
        flat = (flat.astype(np.int64) * top + most // 2) // most  # brightest is `most`
    flat = flat.astype(np.uint16 if most > 255 else np.uint8)
    return flat.reshape((height, width, 3) if depth == 3 else (height, width))


def _bmp(data: bytes) -> np.ndarray:
    """Uncompressed BMP of 1, 4, 8, 16, 24 or 32 bits a pixel, bottom-up or top-down, with or without colour masks (alpha is left out); grey palettes give two axes."""
    if len(data) < 54:
        raise ValueError("a BMP header is cut short")
    start, size, width, height, bits, how = struct.unpack_from("<I", data, 10) + struct.unpack_from("<Iii", data, 14) + struct.unpack_from("<HI", data, 28)
    masked = how in (3, 6)
    if size < 40 or how not in (0, 3, 6) or bits not in (1, 4, 8, 16, 24, 32) or width <= 0 or not height or (masked and bits not in (16, 32)):
        raise ValueError("a BMP image of a kind that is not decoded")
    step, tall = (width * bits + 31) // 32 * 4, abs(height)
    if start + step * tall > len(data):
        raise ValueError("a BMP image is cut short")
    rows = np.frombuffer(data, np.uint8, step * tall, start).reshape(tall, step)
    rows = rows[::-1] if height > 0 else rows
    if bits in (16, 32):
        masks = struct.unpack_from("<III", data, 54) if masked and len(data) >= 66 else (0x7C00, 0x03E0, 0x1F) if bits == 16 else (0xFF0000, 0xFF00, 0xFF)
        if not all(masks):
            raise ValueError("a BMP image with an empty colour mask")
        pixels = np.ascontiguousarray(rows[:, : width * bits // 8]).view(f"<u{bits // 8}").astype(np.uint64)
        return np.stack([_masked(pixels, m) for m in masks], axis=2)
    if bits == 24:
        return rows[:, : width * 3].reshape(tall, width, 3)[:, :, ::-1].copy()
    if bits < 8:
        index = np.unpackbits(rows, axis=1).reshape(tall, -1, bits)
        index = (index << np.arange(bits - 1, -1, -1, dtype=np.uint8)).sum(axis=2, dtype=np.uint8)[:, :width]
    else:
        index = rows[:, :width]
    colours = struct.unpack_from("<I", data, 46)[0] or 1 << bits
    if 14 + size + colours * 4 > len(data) or colours <= int(index.max()):
        raise ValueError("a BMP palette is cut short")
    palette = np.frombuffer(data, np.uint8, colours * 4, 14 + size).reshape(-1, 4)[:, 2::-1]
    pixels = palette[index]
    return pixels[:, :, 0].copy() if (palette == palette[:, :1]).all() else pixels


def _masked(pixels: np.ndarray, mask: int) -> np.ndarray:
    """One colour of masked pixels, stretched to 0 to 255."""
    low = (mask & -mask).bit_length() - 1
    top = mask >> low
    value = (pixels & np.uint64(mask)) >> np.uint64(low)
    return ((value * np.uint64(255) + np.uint64(top // 2)) // np.uint64(top)).astype(np.uint8)


# ---- encoding
def pgm(samples: np.ndarray) -> bytes:
    """Binary grey Netpbm of 8-bit samples."""
    return b"P5\n%d %d\n255\n" % (samples.shape[1], samples.shape[0]) + np.ascontiguousarray(samples, np.uint8).tobytes()


def bmp(samples: np.ndarray) -> bytes:
    """8-bit BMP with a grey palette, bottom-up."""
    height, width = samples.shape
    step = (width + 3) // 4 * 4
    body = np.zeros((height, step), np.uint8)
    body[:, :width] = samples[::-1]
    palette = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 4, axis=1)
    palette[:, 3] = 0
    start = 54 + 1024
    return struct.pack("<2sIHHIIiiHHIIiiII", b"BM", start + body.size, 0, 0, start, 40, width, height, 1, 8, 0, body.size, 2835, 2835, 256, 0) + palette.tobytes() + body.tobytes()


# ---- features
def area_resize(samples: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of the area that each output sample covers, fractions of samples included, from one integral image;
    exact in rational arithmetic up to float64 rounding, for enlarging as well."""
    grey = samples.astype(np.float64)
    if grey.ndim == 3:
        grey = grey @ np.array([0.299, 0.587, 0.114])
    total = np.zeros((grey.shape[0] + 1, grey.shape[1] + 1))
    np.cumsum(np.cumsum(grey, axis=0), axis=1, out=total[1:, 1:])

    def edges(n: int, parts: int) -> tuple[np.ndarray, np.ndarray]:
        cut = np.arange(parts + 1) * n
        return cut // parts, (cut % parts) / parts

    (r, dr), (c, dc) = edges(grey.shape[0], height), edges(grey.shape[1], width)
    down, right = np.minimum(r + 1, grey.shape[0]), np.minimum(c + 1, grey.shape[1])
    rows = total[r] * (1 - dr)[:, None] + total[down] * dr[:, None]
    at = rows[:, c] * (1 - dc) + rows[:, right] * dc
    area = grey.shape[0] / height * grey.shape[1] / width
    return (at[1:, 1:] - at[:-1, 1:] - at[1:, :-1] + at[:-1, :-1]) / area


def difference_hash(samples: np.ndarray) -> str:
    """64 bits: whether each of 8 x 8 areas is darker than the one to its right; sums are rounded so that even areas tie."""
    small = np.round(area_resize(samples, 8, 9), 6)
    return np.packbits(small[:, 1:] > small[:, :-1]).tobytes().hex()


def npy_tile(samples: np.ndarray, side: int = 32) -> bytes:
    """A side x side uint8 thumbnail in NPY form."""
    out = io.BytesIO()
    np.save(out, np.clip(np.rint(area_resize(samples, side, side)), 0, 255).astype(np.uint8), allow_pickle=False)
    return out.getvalue()


def store_payload(payload: bytes, encode=pgm) -> bytes:
    """Bytes as an image ROW samples wide, zeros appended up to a positive multiple of ROW."""
    padded = payload + bytes(-len(payload) % ROW or (0 if payload else ROW))
    return encode(np.frombuffer(padded, np.uint8).reshape(-1, ROW))


# ---- DataFrames
def media_tiles(images: DataFrame, key: str = "key", data: str = "data", side: int = 32) -> DataFrame:
    """key, height, width, channels, tile (NPY bytes), dhash of every image. Where `data` is null, empty or no image that is decoded here, the key stays and the
    other columns are null; a broken image never fails the job. Null keys and repeated rows are kept, other columns ignored, an empty table gives no rows."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for body in batch.column(1).to_pylist():
                try:
                    x = decode(body or b"")
                    found.append((x.shape[0], x.shape[1], x.shape[2] if x.ndim == 3 else 1, npy_tile(x, side), difference_hash(x)))
                except (ValueError, IndexError, OverflowError, struct.error):
                    found.append((None,) * 5)
            kinds = (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([f[i] for f in found], k) for i, k in enumerate(kinds))], ["key", "height", "width", "channels", "tile", "dhash"])

    return images.select(F.col(key).cast("string").alias("key"), F.col(data).alias("data")).mapInArrow(work, "key string, height int, width int, channels int, tile binary, dhash string")


def write_tiles(images: DataFrame, path: str, **options) -> None:
    """Tiles and hashes as a Parquet table, one NPY file's bytes a row."""
    media_tiles(images, **options).write.mode("errorifexists").parquet(path)


def stored_texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and `media`, each text's bytes as a PGM image. Null and empty texts become one row of zeros; null and repeated ids are kept row by row, an empty table
    gives no rows, and other columns are ignored. A text's image is as large as the text."""

    def work(batches):
        for key, body in _parts(batches):
            yield pa.RecordBatch.from_arrays([key, pa.array([store_payload(t.encode()) for t in body], pa.binary())], ["doc_id", "media"])

    return texts(docs, doc_id, text).mapInArrow(work, "doc_id long, media binary")


def payload_report(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per text: stored, decoded again, and described from what was decoded: n_bytes, payload_bytes, payload_sha256, tail_crc32,
    media_bytes, media_sha256, feature (difference hash), tile_sha256.

    One task per input split, no shuffle. Null and empty texts are 64 zeros; repeated rows give equal rows; other columns
    are ignored."""

    def one(text: str) -> tuple:
        raw = text.encode()
        media = store_payload(raw)
        samples = decode(media)
        back = samples.tobytes()
        return len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-ROW:]), len(media), hashlib.sha256(media).hexdigest(), difference_hash(samples), hashlib.sha256(npy_tile(samples)).hexdigest()

    names = ("n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "tile_sha256")
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string())

    def work(batches):
        for key, body in _parts(batches):
            found = list(map(one, body))
            yield pa.RecordBatch.from_arrays([key, *(pa.array([f[i] for f in found], k) for i, k in enumerate(kinds))], ["doc_id", *names])

    schema = "doc_id long, " + ", ".join(f"{n} {'string' if k == pa.string() else 'long'}" for n, k in zip(names, kinds, strict=True))
    return texts(docs, doc_id, text).mapInArrow(work, schema)


def _parts(batches):
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            yield part.column(0), part.column(1).to_pylist()
