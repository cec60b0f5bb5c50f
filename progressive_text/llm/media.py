"""Media columns: Netpbm and BMP images decoded to numpy arrays, resized by area with integral images, kept as NPY tiles
with difference hashes."""

from __future__ import annotations

import hashlib
import io
import re
import struct
import zlib

import numpy as np
from pyspark.sql import DataFrame

from .common import map_rows, saved, whole_text

ROW = 64
_TOKEN = re.compile(rb"(?:\s|#[^\n\r]*[\n\r])*([^\s#]+)")


def encode_netpbm(pixels: np.ndarray) -> bytes:
    """uint8 (height, width) to P5, (height, width, 3) to P6."""
    height, width = pixels.shape[:2]
    return b"%s\n%d %d\n255\n" % (b"P5" if pixels.ndim == 2 else b"P6", width, height) + np.ascontiguousarray(pixels, np.uint8).tobytes()


def decode_netpbm(data: bytes) -> np.ndarray:
    """P1 to P6, up to 16 bits a sample; bit maps give 0 (black) and 1. Damaged images raise ValueError."""
    kind, at = data[:2], 2
    if not re.fullmatch(rb"P[1-6]", kind):
        raise ValueError("not a Netpbm image")
    head = []
    for _ in range(2 if kind in (b"P1", b"P4") else 3):
        m = _TOKEN.match(data, at)
        if not m or not re.fullmatch(rb"[0-9]{1,9}", m[1]):
            raise ValueError("a header without its numbers")
        head.append(int(m[1]))
        at = m.end()
    width, height, most = *head[:2], head[2] if len(head) > 2 else 1
    depth = 3 if kind in (b"P3", b"P6") else 1
    n = width * height * depth
    if not n or not 0 < most < 1 << 16 or n > 8 * len(data):
        raise ValueError("no picture of this size is in the data")
    if kind == b"P1":
        digits = re.sub(rb"#[^\n\r]*|\s", b"", data[at:])[:n]
        if digits.strip(b"01"):
            raise ValueError("a bit that is not 0 or 1")
        flat = 1 - (np.frombuffer(digits, np.uint8).astype(np.int64) - 48)
    elif kind in (b"P2", b"P3"):
        found = re.sub(rb"#[^\n\r]*", b"", data[at:]).split()[:n]
        if not all(re.fullmatch(rb"[0-9]{1,9}", x) for x in found):
            raise ValueError("a sample that is not a number")
        flat = np.array([*map(int, found)], np.int64)
    elif kind == b"P4":
        rows = np.frombuffer(data, np.uint8, (width + 7) // 8 * height, at + 1).reshape(height, -1)
        flat = 1 - np.unpackbits(rows, axis=1)[:, :width]
    else:
        flat = np.frombuffer(data, np.uint8 if most < 256 else ">u2", n, at + 1)
    if flat.size != n or flat.max() > most:
        raise ValueError("samples are missing or above the greatest value")
    flat = flat.astype(np.uint8 if most < 256 else np.uint16)
    return flat.reshape((height, width, 3) if depth == 3 else (height, width))


def encode_bmp(pixels: np.ndarray) -> bytes:
    """uint8 grey (8 bits, grey palette) or RGB (24 bits), rows from the bottom, each filled up to four bytes."""
    height, width = pixels.shape[:2]
    grey = pixels.ndim == 2
    rows = pixels[::-1] if grey else pixels[::-1, :, ::-1]
    rows = np.ascontiguousarray(rows, np.uint8).reshape(height, -1)
    rows = np.pad(rows, ((0, 0), (0, -rows.shape[1] % 4)))
    palette = b"".join(bytes([i, i, i, 0]) for i in range(256)) if grey else b""
    start = 54 + len(palette)
    head = struct.pack("<2sIHHI", b"BM", start + rows.size, 0, 0, start)
    return head + struct.pack("<IiiHHIIiiII", 40, width, height, 1, 8 if grey else 24, 0, rows.size, 2835, 2835, 256 if grey else 0, 0) + palette + rows.tobytes()


def decode_bmp(data: bytes) -> np.ndarray:
    """Uncompressed 1, 4, 8, 24 and 32 bits; a grey palette gives (height, width), other palettes RGB. Damaged images raise
    ValueError."""
    if len(data) < 54:
        raise ValueError("a header without its numbers")
    kind, start, size, width, height, _, bits, packed = struct.unpack_from("<2s8xIIiiHHI", data)
    if kind != b"BM" or packed not in (0, 3) or bits not in (1, 4, 8, 24, 32) or size < 40:
        raise ValueError("not a BMP image of a known kind")
    up, height = height > 0, abs(height)
    stride = (width * bits + 31) // 32 * 4
    if width <= 0 or not height or start + stride * height > len(data):
        raise ValueError("no picture of this size is in the data")
    rows = np.frombuffer(data, np.uint8, stride * height, start).reshape(height, stride)
    rows = rows[::-1] if up else rows
    if bits >= 24:
        return rows[:, : width * bits // 8].reshape(height, width, -1)[:, :, 2::-1].copy()
    at = rows[:, :width] if bits == 8 else np.unpackbits(rows, axis=1)[:, : width * bits].reshape(height, width, bits) @ (1 << np.arange(bits)[::-1])
    used = struct.unpack_from("<I", data, 46)[0] or 1 << bits
    if used > 1 << bits or 14 + size + 4 * used > len(data) or at.max() >= used:
        raise ValueError("a colour that the palette lacks")
    palette = np.frombuffer(data, np.uint8, 4 * used, 14 + size).reshape(-1, 4)[:, 2::-1]
    if (palette == palette[:, :1]).all():
        return palette[:, 0][at]
    return palette[at]


def decode(data: bytes) -> np.ndarray:
    """The pixels of a Netpbm or BMP image; ValueError for whatever else."""
    return decode_bmp(data) if data[:2] == b"BM" else decode_netpbm(data)


def area_resize(pixels: np.ndarray, height: int, width: int) -> np.ndarray:
    """Means over equal areas, from an integral image that is read between its points by weights."""
    grey = pixels.astype(np.float64) if pixels.ndim == 2 else pixels.astype(np.float64) @ np.array([0.299, 0.587, 0.114])
    total = np.pad(grey.cumsum(0).cumsum(1), ((1, 0), (1, 0)))

    def at(edges: np.ndarray, table: np.ndarray) -> np.ndarray:
        low = np.minimum(edges.astype(np.int64), table.shape[0] - 2)
        part = (edges - low).reshape(-1, *[1] * (table.ndim - 1))
        return table[low] * (1 - part) + table[low + 1] * part

    h, w = grey.shape
    rows = at(np.arange(height + 1) * (h / height), total)
    cells = at(np.arange(width + 1) * (w / width), rows.T).T
    return np.diff(np.diff(cells, axis=0), axis=1) / (h / height * w / width)


def difference_hash(pixels: np.ndarray) -> str:
    """64 bits as hex: in an 8 x 9 reduction, whether each cell is darker than the one to its right."""
    small = np.round(area_resize(pixels, 8, 9), 6)
    return np.packbits(small[:, :-1] < small[:, 1:]).tobytes().hex()


def npy_tile(pixels: np.ndarray, side: int = 32) -> bytes:
    """The NPY file of a side x side uint8 reduction."""
    out = io.BytesIO()
    np.save(out, np.clip(np.rint(area_resize(pixels, side, side)), 0, 255).astype(np.uint8), allow_pickle=False)
    return out.getvalue()


def describe(media: DataFrame, column: str = "media", key: str = "doc_id") -> DataFrame:
    """key, height, width, channels, tile (NPY), difference_hash of an image column.

    Null, empty and damaged images (headers without numbers, no or too few samples, samples above the greatest value):
    nulls. Repeated rows, null keys and equal images stay, a row each; other columns of media are left out, whatever
    their names. An image of any size is one row's work; the table of an empty input is empty.
    """

    def make():
        def one(data):
            try:
                pixels = decode(data or b"")
            except ValueError:
                return (None,) * 5
            return pixels.shape[0], pixels.shape[1], 1 if pixels.ndim == 2 else pixels.shape[2], npy_tile(pixels), difference_hash(pixels)

        def each(c):
            found = [one(x) for x in c["media"]]
            return {"key": c["key"], **{k: [x[i] for x in found] for i, k in enumerate(("height", "width", "channels", "tile", "difference_hash"))}}

        return each

    rows = media.selectExpr(f"CAST({key} AS BIGINT) AS key", f"{column} AS media")
    return map_rows(rows, make, "key bigint, height int, width int, channels int, tile binary, difference_hash string").withColumnRenamed("key", key)


def payload(text: str) -> bytes:
    """The text's bytes, with zeros up to a positive multiple of a row."""
    raw = text.encode()
    return raw + bytes(-len(raw) % ROW or (0 if raw else ROW))


NETPBM, BOTH = ("netpbm",), ("netpbm", "bmp")


def text_images(docs: DataFrame, forms: tuple[str, ...] = NETPBM) -> DataFrame:
    """doc_id, n_bytes, media: every whole text (null: empty) as a grey picture of 64 samples a row, P5 or BMP.

    Of several forms a picture takes the one whose place is its number of rows modulo theirs, so equal texts are equal
    pictures and both decoders see every run.
    """
    encoders = [{"netpbm": encode_netpbm, "bmp": encode_bmp}[x] for x in forms]

    def make():
        def picture(text: str) -> bytes:
            pixels = np.frombuffer(payload(text), np.uint8).reshape(-1, ROW)
            return encoders[len(pixels) % len(encoders)](pixels)

        return lambda c: {"doc_id": c["doc_id"], "n_bytes": [len(x.encode()) for x in c["text"]], "media": [picture(x) for x in c["text"]]}

    return map_rows(whole_text(docs), make, "doc_id bigint, n_bytes bigint, media binary")


FEATURES = "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string"


def store_and_describe(docs: DataFrame, forms: tuple[str, ...] = NETPBM, side: int = 32) -> DataFrame:
    """Writes the pictures of all texts as a table, reads their bytes back and describes them; the features and their NPY
    tiles are a second table, and tile_sha256, tile_side and tile_mean come from the tiles read back from it.

    Null texts are empty. Repeated rows and null ids stay; equal texts have equal values in all columns but doc_id. Other
    columns of docs are left out. A text of any length is one row's work.
    """
    stored = saved(text_images(docs, forms), "media")

    def make():
        def each(c):
            pixels = [decode(x) for x in c["media"]]
            raw = [x.tobytes() for x in pixels]
            return {
                "doc_id": c["doc_id"],
                "n_bytes": c["n_bytes"],
                "payload_bytes": [len(x) for x in raw],
                "payload_sha256": [hashlib.sha256(x).hexdigest() for x in raw],
                "tail_crc32": [zlib.crc32(x[-ROW:]) for x in raw],
                "media_bytes": [len(x) for x in c["media"]],
                "media_sha256": [hashlib.sha256(x).hexdigest() for x in c["media"]],
                "feature": [difference_hash(x) for x in pixels],
                "tile": [npy_tile(x, side) for x in pixels],
            }

        return each

    tiles = saved(map_rows(stored, make, f"{FEATURES}, tile binary"), "tiles")

    def read():
        def each(c):
            found = [np.load(io.BytesIO(x), allow_pickle=False) for x in c["tile"]]
            more = {"tile_sha256": [hashlib.sha256(x).hexdigest() for x in c["tile"]], "tile_side": [len(x) for x in found], "tile_mean": [round(float(x.mean()), 6) for x in found]}
            return {k: v for k, v in c.items() if k != "tile"} | more

        return each

    return map_rows(tiles, read, f"{FEATURES}, tile_sha256 string, tile_side int, tile_mean double")
