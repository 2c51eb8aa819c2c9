"""Media columns: Netpbm and BMP images in binary columns, as numpy arrays, resized tiles in NPY form, difference hashes.

``store`` writes encoded images as a Parquet table in the shared folder (as PGM, as BMP, or as one of both by the payload's checksum),
``tiles`` reads such a column back, decodes each image, resizes it by area (differences of an integral image, exact for
fractional edges) and returns NPY bytes and a hash; the query stores the NPY tiles too and takes the feature from what it reads back.

Edge cases: a null or empty payload becomes one row of 64 zero samples in the query; null media gives nulls; unknown or
broken media raises ValueError with its first bytes; equal payloads have equal results; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import io
import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import bounded_batches, materialise, read_table, text_of

WIDTH, TILE = 64, 16


def encode_pgm(image) -> bytes:
    h, w = image.shape
    return b"P5\n%d %d\n255\n" % (w, h) + image.tobytes()


def encode_ppm(image) -> bytes:
    h, w, _ = image.shape
    return b"P6\n%d %d\n255\n" % (w, h) + image.tobytes()


def encode_bmp(image) -> bytes:
    """8-bit grey with a palette, or 24-bit colour; rows bottom up and padded to four bytes."""
    import numpy as np

    h, w = image.shape[:2]
    grey = image.ndim == 2
    rows = image[::-1] if grey else image[::-1, :, ::-1].reshape(h, 3 * w)
    body = np.pad(rows, ((0, 0), (0, -rows.shape[1] % 4))).tobytes()
    palette = b"".join(bytes((i, i, i, 0)) for i in range(256)) if grey else b""
    start = 54 + len(palette)
    head = struct.pack("<2sIHHI", b"BM", start + len(body), 0, 0, start)
    return head + struct.pack("<IiiHHIIiiII", 40, w, h, 1, 8 if grey else 24, 0, len(body), 2835, 2835, 256 if grey else 0, 0) + palette + body


def decode_netpbm(data: bytes):
    """P1 to P6, comments included; samples of up to 8 bits; bitmaps come out as 0 and 255."""
    import re

    import numpy as np

    kind, fields, at = data[1:2], [], 2
    for _ in range(2 if kind in b"14" else 3):
        m = re.compile(rb"(?:\s+|#[^\n]*\n)*(\d+)").match(data, at)
        if not m:
            raise ValueError(f"broken netpbm header: {data[:20]!r}")
        fields.append(int(m[1]))
        at = m.end()
    w, h = fields[:2]
    if fields[2:] and not 0 < fields[2] < 256:
        raise ValueError("samples of more than 8 bits")
    shape = (h, w, 3) if kind in b"36" else (h, w)
    count = h * w * (3 if kind in b"36" else 1)
    if kind in b"123":
        text = re.sub(rb"#[^\n]*", b"", data[at:])
        values = np.array(list(re.sub(rb"\s", b"", text)), np.uint8) - 48 if kind == b"1" else np.array(text.split(), np.uint8)
    elif kind == b"4":
        values = np.unpackbits(np.frombuffer(data, np.uint8, h * -(-w // 8), at + 1).reshape(h, -1), axis=1)[:, :w].ravel()
    else:
        values = np.frombuffer(data, np.uint8, count, at + 1)
    if len(values) < count:
        raise ValueError("netpbm data end early")
    image = values[:count].reshape(shape)
    return np.where(image, 0, 255).astype(np.uint8) if kind in b"14" else image


def decode_bmp(data: bytes):
    """Uncompressed 8-bit palette, 24-bit and 32-bit images; a grey palette gives two dimensions."""
    import numpy as np

    start, size, w, h, _, bits, packing = struct.unpack_from("<I", data, 10) + struct.unpack_from("<IiiHHI", data, 14)
    if packing or bits not in (8, 24, 32):
        raise ValueError(f"BMP with {bits} bits and packing {packing}")
    stride = -(-w * bits // 32) * 4
    rows = np.frombuffer(data, np.uint8, stride * abs(h), start).reshape(abs(h), stride)
    rows = rows[::-1] if h > 0 else rows
    if bits == 8:
        used = struct.unpack_from("<I", data, 46)[0] or 256
        palette = np.frombuffer(data, np.uint8, 4 * used, 14 + size).reshape(-1, 4)[:, 2::-1]
        image = palette[rows[:, :w]]
        return image[:, :, 0] if (palette == palette[:, :1]).all() else image
    return rows[:, : w * bits // 8].reshape(abs(h), w, bits // 8)[:, :, 2::-1]


def decode(data: bytes):
    if data[:2] == b"BM":
        return decode_bmp(data)
    if data[:1] == b"P" and data[1:2] in b"123456" and len(data) > 2:
        return decode_netpbm(data)
    raise ValueError(f"unknown media: {data[:8]!r}")


def area_resize(image, height: int, width: int):
    """Mean over each target cell's area, from the integral image with linear interpolation at fractional edges."""
    import numpy as np

    h, w = image.shape[:2]
    total = np.zeros((h + 1, w + 1, *image.shape[2:]))
    total[1:, 1:] = image.astype(np.float64).cumsum(0).cumsum(1)

    def at(axis_sums, edges):
        low = np.minimum(edges.astype(int), len(axis_sums) - 2)
        part = (edges - low).reshape(-1, *[1] * (axis_sums.ndim - 1))
        return axis_sums[low] * (1 - part) + axis_sums[low + 1] * part

    cells = at(total, np.linspace(0, h, height + 1))
    cells = np.swapaxes(at(np.swapaxes(cells, 0, 1), np.linspace(0, w, width + 1)), 0, 1)
    sums = cells[1:, 1:] - cells[:-1, 1:] - cells[1:, :-1] + cells[:-1, :-1]
    return sums / (h / height * (w / width))


def grey(image):
    return image if image.ndim == 2 else image @ [0.299, 0.587, 0.114]


def difference_hash(image) -> str:
    """64 bits, 16 hex digits: is a cell of the 8 by 9 reduced image darker than the one to its right?"""
    import numpy as np

    small = np.round(area_resize(grey(image), 8, 9), 6)
    return np.packbits(small[:, 1:] > small[:, :-1]).tobytes().hex()


def npy(array) -> bytes:
    import numpy as np

    out = io.BytesIO()
    np.save(out, np.ascontiguousarray(array), allow_pickle=False)
    return out.getvalue()


def store(payloads: DataFrame, key: str, payload: str, codec: str = "pgm", width: int = WIDTH) -> DataFrame:
    """codec: pgm, bmp, or either for one of them by the payload's CRC-32 (even: pgm). Write the bytes in column payload as grey images (key, n_bytes, media) and read them back from the shared folder.

    Bytes are samples in rows of width; zeros fill up the last row, and there is one row at least.
    """
    bounded_batches(payloads.sparkSession)
    encode = {"pgm": (encode_pgm, encode_pgm), "bmp": (encode_bmp, encode_bmp), "either": (encode_pgm, encode_bmp)}[codec]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            sizes, media = [], []
            for x in b.column(1):
                raw = x.as_py() or b""
                rows = max(1, -(-len(raw) // width))
                sizes.append(len(raw))
                media.append(encode[zlib.crc32(raw) % 2](np.frombuffer(raw.ljust(rows * width, b"\0"), np.uint8).reshape(rows, width)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())], names=[key, "n_bytes", "media"])

    kind = payloads.schema[key].dataType.simpleString()
    return materialise(payloads.select(key, payload).mapInArrow(run, f"{key} {kind}, n_bytes long, media binary"), "media")


def tiles(media: DataFrame, keys: list[str], column: str = "media", size: int = TILE) -> DataFrame:
    """The keys, then samples (all of the image's), tile (NPY bytes of the size by size reduction, uint8) and dhash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            samples, tile, marks = [], [], []
            for x in b.column(len(keys)):
                image = decode(x.as_py()) if x.is_valid else None
                samples.append(None if image is None else image.tobytes())
                tile.append(None if image is None else npy(np.round(np.round(area_resize(image, size, size), 6)).astype(np.uint8)))
                marks.append(None if image is None else difference_hash(image))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(samples, pa.binary()), pa.array(tile, pa.binary()), pa.array(marks, pa.string())], names=[*keys, column, "samples", "tile", "dhash"])

    schema = ", ".join(f"`{k}` {media.schema[k].dataType.simpleString()}" for k in [*keys, column])
    return media.select(*keys, column).mapInArrow(run, f"{schema}, samples binary, tile binary, dhash string")


def op7_media_columns(spark, sf_dir: str) -> DataFrame:
    """Whole texts as grey images: stored as PGM or BMP, read back, decoded, digested; their tiles stored as NPY and read back."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", text_of().cast("binary").alias("payload"))
    done = tiles(store(docs, "doc_id", "payload", "either"), ["doc_id", "n_bytes"])
    size = F.octet_length("samples")
    kept = done.select(
        "doc_id", "n_bytes", size.cast("long").alias("payload_bytes"), F.sha2("samples", 256).alias("payload_sha256"),
        F.crc32(F.substring("samples", -64, 64)).alias("tail_crc32"), F.octet_length("media").cast("long").alias("media_bytes"),
        F.sha2("media", 256).alias("media_sha256"), "dhash", "tile",
    )
    back = materialise(kept, "media-tiles")
    return back.withColumn("feature", F.concat_ws(":", "dhash", F.sha2("tile", 256))).drop("dhash", "tile")
