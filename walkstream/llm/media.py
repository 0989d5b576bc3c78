"""Media columns: Netpbm (P2, P3, P5, P6) and BMP (8 and 24 bit, uncompressed) to numpy arrays and back, area resizing by
integral images, NPY tiles and difference hashes.

Defined cases: a null or empty payload is padded to 64 zero bytes in `text_payload`; media that can't be decoded raise
ValueError in `decode` and give null features in `tiles`; a null medium gives null features. Pictures of one row or column
are resized like others.
"""

from __future__ import annotations

import hashlib
import io
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ROW = 64


def _fields(data: bytes, n: int, at: int) -> tuple[list[int], int]:
    """n decimal header fields after white space and comments, and where the single white space after them ends."""
    out = []
    while len(out) < n:
        while at < len(data) and (data[at : at + 1].isspace() or data[at] == 0x23):
            if data[at] == 0x23:
                stop = data.find(b"\n", at)
                at = len(data) if stop < 0 else stop
            at += 1
        to = at
        while to < len(data) and 48 <= data[to] <= 57:
            to += 1
        if to == at:
            raise ValueError("header ends early")
        out.append(int(data[at:to]))
        at = to
    return out, at + 1


def decode_netpbm(data: bytes) -> np.ndarray:
    """Array of rows x columns (x 3); 8-bit samples, or 16-bit ones if the maximum is over 255."""
    kind = data[:2]
    if kind not in (b"P2", b"P3", b"P5", b"P6"):
        raise ValueError("not Netpbm")
    (width, height, top), at = _fields(data, 3, 2)
    if not 0 < top < 65536 or width < 1 or height < 1:
        raise ValueError("bad header")
    shape = (height, width) if kind in (b"P2", b"P5") else (height, width, 3)
    n = int(np.prod(shape))
    if kind in (b"P2", b"P3"):
        values = data[at:].split()
        if len(values) < n:
            raise ValueError("samples are missing")
        return np.array(values[:n], dtype=np.int64).astype(np.uint8 if top < 256 else np.uint16).reshape(shape)
    kind_of = np.dtype(np.uint8 if top < 256 else ">u2")
    if len(data) - at < n * kind_of.itemsize:
        raise ValueError("samples are missing")
    return np.frombuffer(data, dtype=kind_of, count=n, offset=at).reshape(shape)


def encode_netpbm(image: np.ndarray) -> bytes:
    """P5 for rows x columns, P6 for rows x columns x 3; 8-bit samples."""
    kind = b"P5" if image.ndim == 2 else b"P6"
    return b"%s\n%d %d\n255\n" % (kind, image.shape[1], image.shape[0]) + np.ascontiguousarray(image, dtype=np.uint8).tobytes()


def decode_bmp(data: bytes) -> np.ndarray:
    """8-bit palette pictures (grey palettes give rows x columns) and 24-bit ones as red, green, blue."""
    if data[:2] != b"BM" or len(data) < 54:
        raise ValueError("not BMP")
    offset, head, width, height, _, bits, packed = struct.unpack_from("<I I i i H H I", data, 10)
    if packed or bits not in (8, 24) or width < 1 or not height:
        raise ValueError("this kind of BMP isn't handled")
    stride = (width * bits // 8 + 3) // 4 * 4
    if len(data) < offset + stride * abs(height):
        raise ValueError("samples are missing")
    rows = np.frombuffer(data, dtype=np.uint8, count=stride * abs(height), offset=offset).reshape(abs(height), stride)
    rows = rows[::-1] if height > 0 else rows
    if bits == 24:
        return rows[:, : 3 * width].reshape(abs(height), width, 3)[:, :, ::-1]
    used = struct.unpack_from("<I", data, 46)[0] or 256
    palette = np.zeros((256, 4), dtype=np.uint8)
    palette[:used] = np.frombuffer(data, dtype=np.uint8, count=4 * used, offset=14 + head).reshape(used, 4)
    colours = palette[:, 2::-1][rows[:, :width]]
    return colours[:, :, 0] if (palette[:, 0] == palette[:, 1]).all() and (palette[:, 1] == palette[:, 2]).all() else colours


def encode_bmp(image: np.ndarray) -> bytes:
    """8-bit grey or 24-bit BMP, rows from the bottom."""
    height, width = image.shape[:2]
    bits = 8 if image.ndim == 2 else 24
    stride = (width * bits // 8 + 3) // 4 * 4
    rows = np.zeros((height, stride), dtype=np.uint8)
    rows[:, : width * bits // 8] = image if bits == 8 else image[:, :, ::-1].reshape(height, 3 * width)
    palette = b"".join(bytes((i, i, i, 0)) for i in range(256)) if bits == 8 else b""
    offset = 54 + len(palette)
    head = b"BM" + struct.pack("<IHHI", offset + rows.size, 0, 0, offset) + struct.pack("<IiiHHIIiiII", 40, width, height, 1, bits, 0, rows.size, 2835, 2835, 256 if bits == 8 else 0, 0)
    return head + palette + rows[::-1].tobytes()


def decode(data: bytes) -> np.ndarray:
    return decode_bmp(data) if data[:2] == b"BM" else decode_netpbm(data)


def _integral(samples: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """The integral image along axis 0, read at the (fractional) edges; only bands between edges are summed at a time."""
    whole = np.minimum(np.floor(edges).astype(np.int64), len(samples))
    sums, run, last = [], np.zeros(samples.shape[1:]), 0
    for e, w in zip(edges, whole, strict=True):
        run = run + samples[last:w].sum(axis=0, dtype=np.float64)
        last = w
        sums.append(run + (e - w) * samples[w] if w < len(samples) else run)
    return np.array(sums)


def area_resize(image: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean of the source area of each pixel, from differences of the integral image."""
    rows = np.arange(height + 1) * (image.shape[0] / height)
    cols = np.arange(width + 1) * (image.shape[1] / width)
    rows[-1], cols[-1] = image.shape[0], image.shape[1]
    table = np.swapaxes(_integral(np.swapaxes(_integral(image, rows), 0, 1), cols), 0, 1)
    area = (image.shape[0] / height) * (image.shape[1] / width)
    return (table[1:, 1:] - table[:-1, 1:] - table[1:, :-1] + table[:-1, :-1]) / area


def difference_hash(image: np.ndarray) -> str:
    """16 hexadecimal digits: whether each of 8 x 8 cells is darker than the next one in its row."""
    grey = image if image.ndim == 2 else image.mean(axis=2)
    small = np.round(area_resize(grey, 8, 9), 6)
    return np.packbits(small[:, 1:] > small[:, :-1]).tobytes().hex()


def npy_tile(image: np.ndarray, size: int = 32) -> bytes:
    """NPY bytes of the picture resized to size x size."""
    out = io.BytesIO()
    np.save(out, np.clip(np.rint(area_resize(image, size, size)), 0, 255).astype(np.uint8), allow_pickle=False)
    return out.getvalue()


def tiles(media: DataFrame, column: str = "media", size: int = 32) -> DataFrame:
    """Add tile (NPY bytes), dhash, height and width of a binary column; null where it is null or can't be decoded."""

    @F.pandas_udf("tile binary, dhash string, height int, width int")
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for data in batch:
                try:
                    image = decode(bytes(data))
                    rows.append((npy_tile(image, size), difference_hash(image), image.shape[0], image.shape[1]))
                except (ValueError, TypeError, struct.error):
                    rows.append((None, None, None, None))
            yield pd.DataFrame(rows, columns=["tile", "dhash", "height", "width"]).astype({"height": "Int32", "width": "Int32"})

    out = media.withColumn("_t", udf(F.col(column)))
    for c in ("tile", "dhash", "height", "width"):
        out = out.withColumn(c, F.col(f"_t.{c}"))
    return out.drop("_t")


def text_payload(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode()
    return len(raw), raw + bytes(-len(raw) % ROW if raw else ROW)


def store_texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Each text as a P5 picture of 64 columns: doc_id, n_bytes and the medium's bytes."""

    @F.pandas_udf("n_bytes long, media binary")
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            pairs = [text_payload(t if isinstance(t, str) else None) for t in batch]
            yield pd.DataFrame({"n_bytes": [n for n, _ in pairs], "media": [encode_netpbm(np.frombuffer(p, dtype=np.uint8).reshape(-1, ROW)) for _, p in pairs]})

    out = docs.select(F.col(doc_id).alias("doc_id"), udf(F.col(text)).alias("_m"))
    return out.select("doc_id", "_m.n_bytes", "_m.media")


def media_features(stored: DataFrame) -> DataFrame:
    """Read stored media back: digests of the payload and of the medium, the NPY tile's digest and the difference hash."""
    schema = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, tile_sha256 string, feature string"

    @F.pandas_udf(schema)
    def udf(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for data in batch:
                data = bytes(data)
                image = decode(data)
                payload = image.tobytes()
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-ROW:]), len(data), hashlib.sha256(data).hexdigest(), hashlib.sha256(npy_tile(image)).hexdigest(), difference_hash(image)))
            yield pd.DataFrame(rows, columns=[x.split()[0] for x in schema.split(", ")])

    out = stored.withColumn("_f", udf(F.col("media")))
    return out.select("doc_id", "n_bytes", "_f.*")
