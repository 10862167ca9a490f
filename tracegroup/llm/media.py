"""Media columns: texts kept as Netpbm or BMP images, decoded to arrays, area-resized by integral images, tiled as NPY."""

from __future__ import annotations

import io
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracegroup.llm.common import small_batches

UNIT = 192
WIDTH = 64


def payload_of(body: bytes) -> bytes:
    """The bytes, filled up with spaces to a positive multiple of 192."""
    return body + b" " * (-len(body) % UNIT if body else UNIT)


def encode_ppm(samples: np.ndarray) -> bytes:
    """Binary Netpbm of height x width x 3 (or height x width) 8-bit samples."""
    kind = b"P6" if samples.ndim == 3 else b"P5"
    return kind + b"\n%d %d\n255\n" % (samples.shape[1], samples.shape[0]) + samples.tobytes()


def encode_bmp(samples: np.ndarray) -> bytes:
    """Uncompressed 24-bit BMP, rows from the bottom up, blue first, each filled to four bytes."""
    h, w, _ = samples.shape
    row = -(-w * 3 // 4) * 4
    rows = np.zeros((h, row), np.uint8)
    rows[:, : w * 3] = samples[::-1, :, ::-1].reshape(h, w * 3)
    return b"BM" + struct.pack("<IHHI", 54 + rows.size, 0, 0, 54) + struct.pack("<IiiHHIIiiII", 40, w, h, 1, 24, 0, rows.size, 2835, 2835, 0, 0) + rows.tobytes()


def decode(media: bytes) -> np.ndarray:
    """Samples of a Netpbm (P1 to P6, plain or binary, comments allowed) or uncompressed 24 or 32-bit BMP image. ValueError for others."""
    if media[:2] == b"BM":
        return _decode_bmp(media)
    if media[:1] == b"P" and media[1:2] in b"123456" and len(media) > 2:
        return _decode_netpbm(media)
    raise ValueError("neither Netpbm nor BMP")


def _decode_netpbm(media: bytes) -> np.ndarray:
    kind, at, fields = media[1] - 48, 2, []
    need = 2 if kind in (1, 4) else 3
    while len(fields) < need:
        while at < len(media) and media[at] in b" \t\r\n\v\f#":
            at = (media.find(b"\n", at) + 1 or len(media)) if media[at] == 35 else at + 1
        end = at
        while end < len(media) and 48 <= media[end] <= 57:
            end += 1
        if end == at:
            raise ValueError("broken Netpbm header")
        fields.append(int(media[at:end]))
        at = end
    w, h, top = *fields[:2], fields[2] if need == 3 else 1
    depth = 3 if kind in (3, 6) else 1
    if kind < 4:
        rest = b"\n".join(x.split(b"#")[0] for x in media[at:].split(b"\n"))
        values = np.array(list(rest.replace(b" ", b"").replace(b"\n", b"").decode()) if kind == 1 else rest.split(), np.int64)[: w * h * depth]
    elif kind == 4:
        values = np.unpackbits(np.frombuffer(media, np.uint8, -(-w // 8) * h, at + 1).reshape(h, -1), axis=1)[:, :w].ravel()
    else:
        values = np.frombuffer(media, np.uint8 if top < 256 else ">u2", w * h * depth, at + 1)
    if len(values) < w * h * depth:
        raise ValueError("Netpbm data end early")
    if kind in (1, 4):
        values = (1 - values) * 255
    elif top != 255:
        values = values.astype(np.int64) * 255 // max(top, 1)
    out = values.astype(np.uint8).reshape(h, w, depth)
    return out if depth == 3 else out[:, :, 0]


def _decode_bmp(media: bytes) -> np.ndarray:
    start = struct.unpack_from("<I", media, 10)[0]
    w, h, _, bits, packed = struct.unpack_from("<iiHHI", media, 18)
    if bits not in (24, 32) or packed not in (0, 3):
        raise ValueError("only plain 24 and 32-bit BMP")
    row = -(-w * bits // 32) * 4
    rows = np.frombuffer(media, np.uint8, row * abs(h), start).reshape(abs(h), row)[:, : w * bits // 8].reshape(abs(h), w, bits // 8)[:, :, 2::-1]
    return np.ascontiguousarray(rows[::-1] if h > 0 else rows)


def area_resize(grey: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean over each target cell's area, from an integral image read at fractional borders."""
    h, w = grey.shape
    table = np.zeros((h + 1, w + 1))
    table[1:, 1:] = grey.astype(np.float64).cumsum(0).cumsum(1)
    ys, xs = np.linspace(0, h, height + 1), np.linspace(0, w, width + 1)
    y0, x0 = np.minimum(ys.astype(int), h - 1), np.minimum(xs.astype(int), w - 1)
    fy, fx = (ys - y0)[:, None], (xs - x0)[None, :]
    rows = table[y0] * (1 - fy) + table[y0 + 1] * fy
    at = rows[:, x0] * (1 - fx) + rows[:, x0 + 1] * fx
    return (at[1:, 1:] - at[:-1, 1:] - at[1:, :-1] + at[:-1, :-1]) / ((h / height) * (w / width))


def luma(samples: np.ndarray) -> np.ndarray:
    return samples.astype(np.float64) if samples.ndim == 2 else samples @ np.array([0.299, 0.587, 0.114])


def difference_hash(grey: np.ndarray) -> int:
    """64 bits: whether each of 8 x 9 area means is larger than its right neighbour."""
    small = np.round(area_resize(grey, 8, 9), 6)
    return int.from_bytes(np.packbits(small[:, :-1] > small[:, 1:]).tobytes(), "big")


def npy(tile: np.ndarray) -> bytes:
    out = io.BytesIO()
    np.lib.format.write_array(out, np.ascontiguousarray(tile), version=(1, 0), allow_pickle=False)
    return out.getvalue()


def tile_of(samples: np.ndarray, side: int = 16) -> np.ndarray:
    """side x side (x 3) 8-bit tile: every channel area-resized."""
    planes = samples[:, :, None] if samples.ndim == 2 else samples
    small = np.stack([area_resize(planes[:, :, c], side, side) for c in range(planes.shape[2])], 2)
    return np.clip(np.round(small), 0, 255).astype(np.uint8)


def with_media(docs: DataFrame, id_col: str = "doc_id", text: str = "text", form: str = "ppm", side: int = 16) -> DataFrame:
    """Per row of docs: id, n_bytes, the stored image, the payload read back from it, its NPY tile and difference hash.

    A null text counts as empty and fills one unit with spaces. Equal texts give equal values; repeated
    rows stay. Other columns are not read. form: ppm or bmp.
    """
    encode = {"ppm": encode_ppm, "bmp": encode_bmp}[form]

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            step = max(1, min(batch.num_rows, int(batch.num_rows * (4 << 20) / max(batch.nbytes, 1))))
            for a in range(0, batch.num_rows, step):
                yield one(batch.slice(a, step))

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        size, media, back, tiles, hashes = [], [], [], [], []
        for x in batch.column("t").cast(pa.large_binary()).to_pylist():
            body = payload_of(x or b"")
            size.append(len(x or b""))
            media.append(encode(np.frombuffer(body, np.uint8).reshape(-1, WIDTH, 3)))
            samples = decode(media[-1])
            back.append(samples.tobytes())
            tiles.append(npy(tile_of(samples, side)))
            hashes.append(f"{difference_hash(luma(samples)):016x}")
        return pa.RecordBatch.from_arrays([batch.column("id"), pa.array(size, pa.int64()), pa.array(media, pa.binary()), pa.array(back, pa.binary()), pa.array(tiles, pa.binary()), pa.array(hashes)], ["id", "n_bytes", "media", "payload", "tile", "difference_hash"])

    out = small_batches(docs).select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text}`").alias("t")).mapInArrow(run, "id long, n_bytes long, media binary, payload binary, tile binary, difference_hash string")
    return out.withColumnRenamed("id", id_col)


def digests(media: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Sizes and checksums of what with_media() stored and read back; the feature joins the hash and the tile's checksum."""
    return media.select(
        id_col,
        "n_bytes",
        F.octet_length("payload").cast("long").alias("payload_bytes"),
        F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, octet_length(payload) - 15, 16)")).alias("tail_crc32"),
        F.octet_length("media").cast("long").alias("media_bytes"),
        F.sha2("media", 256).alias("media_sha256"),
        F.concat_ws("-", F.col("difference_hash"), F.lpad(F.lower(F.hex(F.crc32("tile"))), 8, "0")).alias("feature"),
    )

