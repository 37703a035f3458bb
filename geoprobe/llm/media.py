"""Media columns: texts kept as PNG images in a binary column, read back and fingerprinted.

`store_media` writes each text's UTF-8 bytes, filled up with bytes 255 to a positive multiple of 576, as one
8-bit greyscale image of 576 samples a row; each row has the filter with the least sum of absolute differences. `read_media` parses the
chunks, tests every checksum, inflates, undoes the row filters with numpy (all images of a batch together: a sample needs its left, upper and corner neighbours, so samples
on one diagonal are undone at once) and hashes the low frequencies of the image's cosine transform.

Null text is stored as the empty text (one row of 255s); equal texts give equal media and features; repeated rows
stay; other columns are ignored; a damaged image raises ValueError.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_binary, map_text

UNIT = 576
LEVEL = 6
#: Fixed values of the PNG format: signature, largest chunk written here.
SIGNATURE = b"\x89PNG\r\n\x1a\n"
CHUNK = 1 << 16
#: Rows that are filtered at a time.
BAND = 4096
#: Low frequencies kept: an 8 x 8 corner of the transform of a 32 x 32 reduction.
SIDE, KEPT = 32, 8


def padded(data: bytes) -> bytes:
    return data + b"\xff" * (max(1, -(-len(data) // UNIT)) * UNIT - len(data))


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def _predict(left, up, corner):
    base = left + up - corner
    a, b, c = abs(base - left), abs(base - up), abs(base - corner)
    return np.where((a <= b) & (a <= c), left, np.where(b <= c, up, corner))


def _neighbours(rows: np.ndarray, step: int, first: np.ndarray):
    """Left, upper and corner samples of every sample as 16-bit numbers; zero outside the image (`first`: its first rows)."""
    x = rows.astype(np.int16)
    left, up, corner = np.zeros_like(x), np.zeros_like(x), np.zeros_like(x)
    left[:, step:], up[1:] = x[:, :-step], x[:-1]
    up[first] = 0
    corner[:, step:] = up[:, :-step]
    return x, left, up, corner


def filtered(rows: np.ndarray, kinds: np.ndarray | None = None, step: int = 1, first: np.ndarray | None = None) -> np.ndarray:
    """PNG rows, each after the number of its filter (0 none, 1 left, 2 above, 3 mean, 4 predictor); without `kinds` each row
    takes the filter with the least sum of absolute differences, the lowest of equals. The rows may be those of several
    images one below the other, which start at `first`."""
    first = np.array([0]) if first is None else first
    if len(rows) > BAND:
        # Bands with one row of the band before, so that a long text takes no more memory than a band.
        out = []
        for a in range(0, len(rows), BAND):
            b, lead = min(len(rows), a + BAND), min(a, 1)
            inside = first[(first >= a) & (first < b)] - a + lead
            own = None if kinds is None else kinds[a - lead : b]
            out.append(filtered_band(rows[a - lead : b], own, step, np.append(inside, 0))[lead:])
        return np.concatenate(out)
    return filtered_band(rows, kinds, step, first)


def filtered_band(rows: np.ndarray, kinds: np.ndarray | None, step: int, first: np.ndarray) -> np.ndarray:
    x, left, up, corner = _neighbours(rows, step, first)
    made = [rows, *(((x - guess) & 255).astype(np.uint8) for guess in (left, up, (left + up) >> 1, _predict(left, up, corner)))]
    if kinds is None:
        kinds = np.argmin([np.abs(m.view(np.int8).astype(np.int16)).sum(axis=1, dtype=np.int64) for m in made], axis=0)
    out = np.empty((len(rows), rows.shape[1] + 1), np.uint8)
    out[:, 0] = kinds
    for kind, m in enumerate(made):
        out[kinds == kind, 1:] = m[kinds == kind]
    return out


def _png(body: np.ndarray, level: int) -> bytes:
    packed = zlib.compress(body.tobytes(), level)
    head = struct.pack(">IIBBBBB", body.shape[1] - 1, len(body), 8, 0, 0, 0, 0)
    data = b"".join(_chunk(b"IDAT", packed[i : i + CHUNK]) for i in range(0, len(packed), CHUNK))
    return SIGNATURE + _chunk(b"IHDR", head) + data + _chunk(b"IEND", b"")


def encode_pngs(payloads: list[bytes], width: int = UNIT, kind: int | None = None, level: int = LEVEL) -> list[bytes]:
    """A greyscale image for each payload, a multiple of `width` bytes; every row under one filter, or under its best."""
    if not payloads:
        return []
    rows = np.frombuffer(b"".join(payloads), np.uint8).reshape(-1, width)
    starts = np.cumsum([0, *(len(p) // width for p in payloads)])
    body = filtered(rows, None if kind is None else np.full(len(rows), kind), first=starts[:-1])
    return [_png(body[a:b], level) for a, b in zip(starts[:-1], starts[1:], strict=True)]


def encode_png(payload: bytes, width: int = UNIT, kind: int | None = None, level: int = LEVEL) -> bytes:
    return encode_pngs([payload], width, kind, level)[0]


def chunks_of(image: bytes):
    """The chunks of a PNG, each after its checksum test."""
    if image[:8] != SIGNATURE:
        raise ValueError("not a PNG")
    at = 8
    while at < len(image):
        (size,) = struct.unpack_from(">I", image, at)
        kind, body = image[at + 4 : at + 8], image[at + 8 : at + 8 + size]
        if len(image) < at + 12 + size or zlib.crc32(kind + body) != struct.unpack_from(">I", image, at + 8 + size)[0]:
            raise ValueError(f"damaged chunk {kind!r}")
        yield kind, body
        at += 12 + size


def unfilter(body: np.ndarray, step: int = 1, first: np.ndarray | None = None) -> np.ndarray:
    """Undo the row filters of images of one width, one below the other, which start at the rows `first`.

    Sample j of row i needs j - step of its row and both above, so all samples with the same i + j (in pixels) are undone
    at once, in all images: as many steps as a row and the longest image have pixels. Where no row has a sequential filter
    (1, 3, 4) whole rows are undone at once."""
    kinds, rows = body[:, 0], body[:, 1:]
    if kinds.max(initial=0) > 4:
        raise ValueError(f"unknown row filter {kinds.max()}")
    first = np.array([0]) if first is None else first
    if not kinds.any():
        return rows.copy()
    number = np.arange(len(rows)) - np.repeat(first, np.diff(np.append(first, len(rows))))
    if not np.isin(kinds, (1, 3, 4)).any():
        out = rows.copy()
        for i in range(1, int(number.max(initial=0)) + 1):
            here = np.flatnonzero((number == i) & (kinds == 2))
            out[here] += out[here - 1]
        return out
    width = rows.shape[1] // step
    # A column of zeros on the left and a row of zeros on the top stand for what lies outside; rows in order of their place
    # in their image, so that those of one diagonal are neighbours in memory.
    order = np.argsort(number, kind="stable")
    place = np.empty_like(order)
    place[order] = np.arange(len(order))
    above = np.where(number[order] > 0, place[np.maximum(order - 1, 0)], len(rows))
    kind, code = kinds[order].astype(np.int16)[:, None], rows[order].reshape(len(rows), width, step)
    out = np.zeros((width + 1, len(rows) + 1, step), np.int16)
    counts = np.searchsorted(number[order], np.arange(int(number.max()) + 2))
    for turn in range(width + int(number.max())):
        low, high = max(0, turn - width + 1), min(turn, int(number.max()))
        r = np.arange(counts[low], counts[high + 1])
        j = turn - number[order][r]
        up_row, k = above[r], kind[r]
        left, up, corner = out[j, r], out[j + 1, up_row], out[j, up_row]
        guess = np.where(k == 4, _predict(left, up, corner), np.where(k == 3, (left + up) >> 1, np.where(k == 2, up, np.where(k == 1, left, 0))))
        out[j + 1, r] = (code[r, j] + guess) & 255
    return out[1:, place].transpose(1, 0, 2).reshape(rows.shape).astype(np.uint8)


def _parsed(image: bytes) -> tuple[int, int, np.ndarray]:
    """Samples a pixel, width in pixels and filtered rows of an 8-bit image without interlacing or palette."""
    head, packed, ended = None, [], False
    for kind, body in chunks_of(image):
        if kind == b"IHDR":
            head = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            packed.append(body)
        ended |= kind == b"IEND"
    if head is None or not ended or head[2] != 8 or head[3] not in (0, 2, 4, 6) or any(head[4:]):
        raise ValueError("unsupported or cut PNG")
    step = {0: 1, 2: 3, 4: 2, 6: 4}[head[3]]
    return step, head[0], np.frombuffer(zlib.decompress(b"".join(packed)), np.uint8).reshape(head[1], head[0] * step + 1)


def decode_pngs(images: list[bytes]) -> list[np.ndarray]:
    """Rows x samples of each image; images of one shape of rows are unfiltered together."""
    parsed = [_parsed(image) for image in images]
    out: list[np.ndarray] = [np.zeros((0, 0), np.uint8)] * len(images)
    for shape in {p[:2] for p in parsed}:
        own = [i for i, p in enumerate(parsed) if p[:2] == shape]
        starts = np.cumsum([0, *(len(parsed[i][2]) for i in own)])
        rows = unfilter(np.concatenate([parsed[i][2] for i in own]), shape[0], starts[:-1])
        for i, a, b in zip(own, starts[:-1], starts[1:], strict=True):
            out[i] = rows[a:b]
    return out


def decode_png(image: bytes) -> np.ndarray:
    return decode_pngs([image])[0]


_TURN = np.cos(np.pi / SIDE * (np.arange(SIDE)[None, :] + 0.5) * np.arange(KEPT)[:, None])


def reduced(pixels: np.ndarray, side: int = SIDE) -> np.ndarray:
    """Mean over a side x side grid; an axis shorter than the grid repeats its samples."""
    out = pixels
    for axis in (0, 1):
        n = out.shape[axis]
        edges = np.arange(side) * n // side
        if n < side:
            out = np.take(out, edges, axis=axis).astype(np.float64)
        else:
            sizes = np.diff(np.append(edges, n)).reshape((-1, 1) if axis == 0 else (1, -1))
            out = np.add.reduceat(out, edges, axis=axis, dtype=np.float64) / sizes
    return out


def cosine_hash(pixels: np.ndarray) -> bytes:
    """64 bits: which low frequencies lie above their median, the constant term left out of the median."""
    low = np.round(_TURN @ reduced(pixels) @ _TURN.T, 6).reshape(-1)
    return np.packbits(low > np.median(low[1:])).tobytes()


def store_media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media (PNG)."""

    def run(batch: pa.RecordBatch) -> dict:
        texts = as_binary(batch.column("text"))
        return {"doc_id": batch.column("doc_id"), "n_bytes": [len(t) for t in texts], "media": encode_pngs([padded(t) for t in texts])}

    return map_text(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, "doc_id long, n_bytes long, media binary")


def read_media(stored: DataFrame) -> DataFrame:
    """doc_id, n_bytes and, from the stored bytes alone, payload size and digests, media size and digest, hash."""

    def run(batch: pa.RecordBatch) -> dict:
        out: dict[str, list] = {k: [] for k in ("payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "cosine_hash")}
        images = as_binary(batch.column("media"))
        for image, pixels in zip(images, decode_pngs(images), strict=True):
            payload = pixels.tobytes()
            for k, v in zip(out, (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(image), hashlib.sha256(image).hexdigest(), cosine_hash(pixels)), strict=True):
                out[k].append(v)
        return {"doc_id": batch.column("doc_id"), "n_bytes": batch.column("n_bytes")} | out

    return map_text(stored.select("doc_id", "n_bytes", "media"), run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, cosine_hash binary", column="media")
