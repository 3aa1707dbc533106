"""Media columns: Netpbm and BMP codecs on numpy arrays, area resizing by integral images, NPY tiles, difference hashes."""

from __future__ import annotations

import hashlib
import io
import re
import struct
import uuid
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_text, file_system, fresh_path, stored, tidy, to_frame, whole

MEDIA = "doc_id long, n_bytes long, media binary"
HEADER = re.compile(rb"(P[1-6])(?:\s+(?:#[^\n]*\n\s*)*)(\d+)(?:\s+(?:#[^\n]*\n\s*)*)(\d+)")


def write_netpbm(pixels: np.ndarray) -> bytes:
    """Binary PGM of a (height, width) array, PPM of (height, width, 3); 8-bit samples."""
    kind = b"P5" if pixels.ndim == 2 else b"P6"
    return kind + b"\n%d %d\n255\n" % (pixels.shape[1], pixels.shape[0]) + np.ascontiguousarray(pixels, np.uint8).tobytes()


def read_netpbm(data: bytes) -> np.ndarray:
    """Any of the six kinds, plain and binary, 8 or 16 bits; comments allowed. Bitmaps decode to 0 (black) and 255."""
    head = HEADER.match(data)
    if not head:
        raise ValueError("not a Netpbm file")
    kind, width, height, at = head[1], int(head[2]), int(head[3]), head.end()
    channels = 3 if kind in (b"P3", b"P6") else 1
    shape = (height, width, 3) if channels == 3 else (height, width)
    if kind in (b"P1", b"P4"):
        if kind == b"P1":
            bits = np.frombuffer(re.sub(rb"#[^\n]*|\s", b"", data[at:]), np.uint8)[: height * width] - 48
        else:
            stride = (width + 7) // 8
            raw = np.frombuffer(data, np.uint8, stride * height, at + 1).reshape(height, stride)
            bits = np.unpackbits(raw, axis=1)[:, :width].ravel()
        return ((1 - bits) * 255).astype(np.uint8).reshape(shape)
    most = re.match(rb"\s+(?:#[^\n]*\n\s*)*(\d+)", data[at:])
    top, at = int(most[1]), at + most.end()
    n = height * width * channels
    if kind in (b"P2", b"P3"):
        values = np.array(re.sub(rb"#[^\n]*", b"", data[at:]).split()[:n], np.int64)
    else:
        values = np.frombuffer(data, np.uint8 if top < 256 else ">u2", n, at + 1)
    if len(values) != n:
        raise ValueError("pixels are missing")
    if top != 255:
        values = (values.astype(np.int64) * 255 + top // 2) // top
    return values.astype(np.uint8).reshape(shape)


def write_bmp(pixels: np.ndarray) -> bytes:
    """Uncompressed BMP: 8-bit grey with its palette, or 24-bit colour."""
    height, width = pixels.shape[:2]
    grey = pixels.ndim == 2
    body = pixels if grey else pixels[:, :, ::-1]
    rows = np.ascontiguousarray(body[::-1], np.uint8).reshape(height, -1)
    rows = np.pad(rows, ((0, 0), (0, -rows.shape[1] % 4)))
    palette = np.repeat(np.arange(256, dtype=np.uint8), 4).reshape(256, 4) * np.array([1, 1, 1, 0], np.uint8) if grey else np.zeros(0, np.uint8)
    at = 54 + palette.size
    head = b"BM" + struct.pack("<IHHI", at + rows.size, 0, 0, at)
    info = struct.pack("<IiiHHIIiiII", 40, width, height, 1, 8 if grey else 24, 0, rows.size, 2835, 2835, 256 if grey else 0, 0)
    return head + info + palette.tobytes() + rows.tobytes()


def read_bmp(data: bytes) -> np.ndarray:
    """Uncompressed BMP of 1, 4, 8, 24 or 32 bits, bottom-up or top-down; a grey palette gives a grey array."""
    if data[:2] != b"BM":
        raise ValueError("not a BMP file")
    at, size = struct.unpack_from("<I", data, 10)[0], struct.unpack_from("<I", data, 14)[0]
    width, height, _, depth, packed = struct.unpack_from("<iiHHI", data, 18)
    if packed not in (0, 3):
        raise ValueError("compressed BMP is not supported")
    flip, height = height > 0, abs(height)
    stride = (width * depth + 31) // 32 * 4
    rows = np.frombuffer(data, np.uint8, stride * height, at).reshape(height, stride)
    if flip:
        rows = rows[::-1]
    if depth in (24, 32):
        return rows[:, : width * depth // 8].reshape(height, width, depth // 8)[:, :, 2::-1].copy()
    used = struct.unpack_from("<I", data, 46)[0] or 1 << depth
    palette = np.frombuffer(data, np.uint8, used * 4, 14 + size).reshape(-1, 4)[:, 2::-1]
    if depth == 8:
        codes = rows[:, :width]
    else:
        bits = np.unpackbits(rows, axis=1).reshape(height, -1, depth)
        codes = (bits * (1 << np.arange(depth)[::-1])).sum(axis=2)[:, :width]
    pixels = palette[codes]
    return pixels[:, :, 0].copy() if (palette[:, 0] == palette[:, 1]).all() and (palette[:, 1] == palette[:, 2]).all() else pixels


def decode(data: bytes) -> np.ndarray:
    return read_bmp(data) if data[:2] == b"BM" else read_netpbm(data)


def grey(pixels: np.ndarray) -> np.ndarray:
    return pixels if pixels.ndim == 2 else (pixels.astype(np.float64) @ np.array([0.299, 0.587, 0.114])).round().astype(np.uint8)


def resize_area(pixels: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of the source area under each target pixel, with fractional borders, from one integral image."""
    source = pixels.astype(np.float64)
    h, w = source.shape
    total = np.zeros((h + 1, w + 1))
    np.cumsum(np.cumsum(source, axis=0), axis=1, out=total[1:, 1:])

    def edges(n: int, m: int):
        x = np.arange(m + 1) * (n / m)
        low = np.minimum(x.astype(int), n - 1)
        return low, x - low

    (y0, fy), (x0, fx) = edges(h, height), edges(w, width)
    by_row = total[y0] * (1 - fy)[:, None] + total[y0 + 1] * fy[:, None]
    grid = by_row[:, x0] * (1 - fx) + by_row[:, x0 + 1] * fx
    sums = grid[1:, 1:] - grid[:-1, 1:] - grid[1:, :-1] + grid[:-1, :-1]
    return sums / ((h / height) * (w / width))


def difference_hash(pixels: np.ndarray, size: int = 8) -> str:
    """Hex of size*size bits: is a cell of the resized image less than its right neighbour?"""
    small = np.floor(resize_area(grey(pixels), size, size + 1) * 256 + 0.5)
    return np.packbits(small[:, :-1] < small[:, 1:]).tobytes().hex()


def tile(pixels: np.ndarray, side: int) -> np.ndarray:
    """The image resized to a square of 8-bit samples."""
    return np.clip(np.floor(resize_area(grey(pixels), side, side) + 0.5), 0, 255).astype(np.uint8)


def text_payload(data: bytes, unit: int = 64) -> bytes:
    """The bytes, then zeros up to a positive multiple of the unit."""
    return data + b"\0" * (max(unit, -(-len(data) // unit) * unit) - len(data))


def to_media(docs: DataFrame, width: int = 64, form: str = "pgm") -> DataFrame:
    """(doc_id, n_bytes, media): each text's padded UTF-8 bytes as the samples of a grey image of the given width.

    Null text is empty and gives one row of zeros; very long texts give tall images; null ids are kept, repeated rows are
    images of their own, an empty table gives none, other columns are ignored."""

    def make(frames):
        write = write_bmp if form == "bmp" else write_netpbm
        for frame in frames:
            raw = [t.encode("utf-8", "surrogatepass") for t in frame["text"]]
            keys = whole(frame["doc_id"])
            for a in range(0, len(raw), 500):
                yield to_frame([(k, len(r), write(np.frombuffer(text_payload(r, width), np.uint8).reshape(-1, width))) for k, r in zip(keys[a : a + 500], raw[a : a + 500], strict=True)], MEDIA)

    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text"))
    return chosen.mapInPandas(tidy(make), MEDIA)


FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
TILED = FEATURES + ", tile_path string, tile_row long"
DESCRIBED = FEATURES + ", tile_sha256 string, preview_bytes long, preview_sha256 string"


def write_tiles(media: DataFrame, folder: str, side: int = 16, per_file: int = 4096) -> DataFrame:
    """Decode stored media, describe each image, and write the resized images as NPY files of shape (n, side, side).

    Gives one row per image: what was read back, and the file and row of its tile. Equal media give equal values. A task
    writes each file under a name of its own, so a retried task leaves a file that no row names. An empty table gives no
    row and no file."""

    def save(frames):
        store, base = file_system(folder)
        rows, tiles = [], []

        def flush():
            store.create_dir(base, recursive=True)
            name = f"{base}/tiles-{uuid.uuid4().hex}.npy"
            sink = io.BytesIO()
            np.save(sink, np.stack(tiles), allow_pickle=False)
            with store.open_output_stream(name) as out:
                out.write(sink.getvalue())
            path = name if "://" not in folder and not folder.startswith("file:") else folder.rstrip("/") + name[len(base) :]
            return to_frame([(*r, path, i) for i, r in enumerate(rows)], TILED)

        for frame in frames:
            for doc_id, n, data in zip(whole(frame["doc_id"]), frame["n_bytes"], frame["media"], strict=True):
                pixels = decode(bytes(data))
                payload = pixels.tobytes()
                rows.append((doc_id, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(data), hashlib.sha256(data).hexdigest(), difference_hash(pixels)))
                tiles.append(tile(pixels, side))
                if len(rows) == per_file:
                    yield flush()
                    rows, tiles = [], []
        if rows:
            yield flush()

    return media.select("doc_id", "n_bytes", "media").mapInPandas(tidy(save), TILED)


def read_tiles(written: DataFrame) -> DataFrame:
    """Read every tile back from its file, and tell its digest and that of its BMP form, which must decode to the same tile."""

    def load(frames):
        held: dict[str, np.ndarray] = {}
        for frame in frames:
            rows = []
            for r in frame.itertuples(index=False):
                if r.tile_path not in held:
                    held.clear()  # rows of one file stand together
                    store, name = file_system(r.tile_path)
                    with store.open_input_stream(name) as source:
                        held[r.tile_path] = np.load(io.BytesIO(source.read()), allow_pickle=False)
                found = held[r.tile_path][int(r.tile_row)]
                preview = write_bmp(found)
                if not np.array_equal(read_bmp(preview), found):
                    raise ValueError("a preview differs from its tile")
                rows.append((*r[:-2], hashlib.sha256(found.tobytes()).hexdigest(), len(preview), hashlib.sha256(preview).hexdigest()))
            yield to_frame([(None if r[0] is None or r[0] != r[0] else int(r[0]), *r[1:]) for r in rows], DESCRIBED)

    return written.mapInPandas(tidy(load), DESCRIBED)


def text_media(docs: DataFrame, width: int = 64, form: str = "pgm", side: int = 16) -> DataFrame:
    """Store every text as media in the shared folder, read it back, describe it, and write and read back its tile.

    (doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature, tile_sha256,
    preview_bytes, preview_sha256) for each row; the cases are those of to_media()."""
    media = stored(to_media(docs, width, form), "media")
    return read_tiles(stored(write_tiles(media, fresh_path(docs.sparkSession, "tiles"), side), "tiled"))
