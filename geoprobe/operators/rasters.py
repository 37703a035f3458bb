"""Rasters of whole texts and the input changes that probe a model: cue removal, random masks, edges, blur, scrambling.

All kernels are numpy functions of one raster; they run inside Arrow batches next to the model, so a raster is made once and
never shuffled. Random choices depend on the seed and the image alone."""

from __future__ import annotations

import heapq
import re
from functools import lru_cache

import numpy as np

SIDE, CHANNELS = 56, 3
#: The same cues as in the native coverage operator.
_CUES = {
    "short_word": re.compile(r"(?<![^\W\d_])[^\W\d_]{1,3}(?![^\W\d_])"), "sentence_head": re.compile(r"(?<![^\W\d_])[A-ZÀ-ÖØ-Þ][^\W\d_]*"),
    "license_line": re.compile(r"(?im)^[^\n]*(?:license|licence|copyright|spdx)[^\n]*$"), "contact_secret": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+|\d[\d.\-]{7,}\d"),
}
CUES = tuple(_CUES)


@lru_cache(maxsize=1)
def _codes() -> np.ndarray:
    """Three channels for every character below 0x3000: letter identity, character class, case or accent."""
    import unicodedata

    out = np.zeros((0x3000, CHANNELS), np.float32)
    for c in range(0x3000):
        ch = chr(c)
        base = unicodedata.normalize("NFD", ch)[0].lower()
        out[c] = ((ord(base) % 32) * 8 if ch.isalpha() else 0, 255 if ch.isalpha() else 128 if ch.isdigit() else 0, 255 if c > 127 else 128 if ch.isupper() else 0)
    return out


def _layout(values: np.ndarray, side: int) -> np.ndarray:
    """Lay a sequence out row by row in the smallest square of at least `side` columns, then reduce it to side x side by area means."""
    wide = max(side, int(np.ceil(np.sqrt(len(values)))))
    full = np.zeros((wide * wide, values.shape[1]), np.float32)
    full[: len(values)] = values
    full = full.reshape(wide, wide, -1)
    if wide == side:
        return full
    edges = np.arange(side) * wide // side
    sizes = np.diff(np.append(edges, wide)).astype(np.float32)
    out = np.add.reduceat(np.add.reduceat(full, edges, axis=0), edges, axis=1)
    return out / sizes[:, None, None] / sizes[None, :, None]


def of_text(text: str, side: int = SIDE) -> np.ndarray:
    """A side x side x 3 raster (0 to 255) of a whole text; the empty text is black."""
    codes = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)
    return _layout(_codes()[np.minimum(codes, 0x2FFF)], side)


def to_bytes(raster: np.ndarray) -> bytes:
    """A raster as 8-bit samples, row by row."""
    return np.clip(np.round(raster), 0, 255).astype(np.uint8).tobytes()


def from_bytes(data: bytes, side: int = SIDE) -> np.ndarray:
    return np.frombuffer(data, np.uint8).reshape(side, side, -1).astype(np.float32)


def cue_mask(text: str, cue: str, side: int = SIDE) -> np.ndarray:
    """Which pixels hold at least half cue characters (any share where the cue is sparse)."""
    mark = np.zeros((max(1, len(text)), 1), np.float32)
    for m in _CUES[cue].finditer(text):
        mark[m.start() : m.end()] = 1
    share = _layout(mark, side)[:, :, 0]
    return share >= 0.5 if cue in ("short_word", "sentence_head") else share > 0


def preprocessed(raster: np.ndarray, mean: float = 96.0, spread: float = 96.0) -> np.ndarray:
    return (raster - mean) / spread


def generator(seed: int, image: int, purpose: str) -> np.random.Generator:
    return np.random.default_rng([seed, image & 0xFFFFFFFF, *purpose.encode()])


def random_mask(mask: np.ndarray, seed: int, image: int, cue: str, shape: str = "scatter") -> np.ndarray:
    """As many pixels as `mask`: scattered, or the same shape displaced cyclically."""
    rng = generator(seed, image, f"mask:{cue}")
    if shape == "shift":
        return np.roll(mask, (int(rng.integers(1, mask.shape[0])), int(rng.integers(1, mask.shape[1]))), axis=(0, 1))
    out = np.zeros(mask.size, bool)
    out[rng.permutation(mask.size)[: int(mask.sum())]] = True
    return out.reshape(mask.shape)


def inpainted(raster: np.ndarray, mask: np.ndarray, fill: str = "mean", reach: int = 3) -> np.ndarray:
    """The raster with masked pixels filled: zero, mean of the rest, or fast marching from the mask's edge inwards, each
    pixel a distance- and direction-weighted mean of the known ones around it."""
    out = raster.astype(np.float32).copy()
    if not mask.any():
        return out
    if fill == "zero" or mask.all():
        out[mask] = 0
        return out
    if fill == "mean":
        out[mask] = out[~mask].mean(axis=0)
        return out
    h, w = mask.shape
    far = np.where(mask, np.inf, 0.0)
    known, heap = ~mask, []
    steps = ((0, 1), (1, 0), (0, -1), (-1, 0))

    def arrival(y, x):
        a = min((far[y, q] for q in (x - 1, x + 1) if 0 <= q < w), default=np.inf)
        b = min((far[q, x] for q in (y - 1, y + 1) if 0 <= q < h), default=np.inf)
        a, b = min(a, b), max(a, b)
        return a + 1 if b - a >= 1 or not np.isfinite(b) else (a + b + np.sqrt(2 - (b - a) ** 2)) / 2

    for y, x in zip(*np.nonzero(mask), strict=True):
        if any(0 <= y + i < h and 0 <= x + j < w and known[y + i, x + j] for i, j in steps):
            heapq.heappush(heap, (1.0, int(y), int(x)))
    while heap:
        t, y, x = heapq.heappop(heap)
        if known[y, x]:
            continue
        y0, y1, x0, x1 = max(0, y - reach), min(h, y + reach + 1), max(0, x - reach), min(w, x + reach + 1)
        near = known[y0:y1, x0:x1]
        gy, gx = np.mgrid[y0:y1, x0:x1]
        dy, dx = y - gy[near], x - gx[near]
        dist = dy * dy + dx * dx
        slope_y = (far[min(h - 1, y + 1), x] if y + 1 < h and known[y + 1, x] else t) - (far[y - 1, x] if y and known[y - 1, x] else t)
        slope_x = (far[y, min(w - 1, x + 1)] if x + 1 < w and known[y, x + 1] else t) - (far[y, x - 1] if x and known[y, x - 1] else t)
        weight = np.maximum(np.abs(dy * slope_y + dx * slope_x) / np.sqrt(dist), 1e-3) / dist / (1 + np.abs(far[y0:y1, x0:x1][near] - t))
        out[y, x] = (out[y0:y1, x0:x1][near] * weight[:, None]).sum(axis=0) / weight.sum()
        far[y, x], known[y, x] = t, True
        for i, j in steps:
            if 0 <= y + i < h and 0 <= x + j < w and not known[y + i, x + j]:
                heapq.heappush(heap, (float(arrival(y + i, x + j)), y + i, x + j))
    return out


def _gauss(sigma: float) -> np.ndarray:
    r = max(1, int(np.ceil(3 * sigma)))
    k = np.exp(-0.5 * (np.arange(-r, r + 1) / sigma) ** 2)
    return (k / k.sum()).astype(np.float32)


def _filtered(x: np.ndarray, k: np.ndarray, axis: int) -> np.ndarray:
    r = len(k) // 2
    pad = [(0, 0)] * x.ndim
    pad[axis] = (r, r)
    p = np.pad(x, pad, mode="edge")
    return sum(k[i] * np.take(p, range(i, i + x.shape[axis]), axis=axis) for i in range(len(k)))


def blurred(raster: np.ndarray, sigma: float | None = None) -> np.ndarray:
    """Separable Gaussian blur; by default sigma is a 28th of the side."""
    k = _gauss(sigma or raster.shape[0] / 28)
    return _filtered(_filtered(raster.astype(np.float32), k, 0), k, 1)


def edges(raster: np.ndarray, low: float = 100, high: float = 200, sigma: float = 1.4) -> np.ndarray:
    """Edge map: smoothing, gradients, thinning along the gradient, and weak edges kept where they touch strong ones."""
    grey = blurred(raster.mean(axis=2, keepdims=True), sigma)[:, :, 0]
    smooth, slope = np.array([1, 2, 1], np.float32), np.array([-1, 0, 1], np.float32)
    gx, gy = _filtered(_filtered(grey, smooth, 0), slope, 1), _filtered(_filtered(grey, smooth, 1), slope, 0)
    size = np.hypot(gx, gy)
    angle = (np.round(np.arctan2(gy, gx) / (np.pi / 4)).astype(int)) % 4
    p = np.pad(size, 1)
    keep = np.zeros(size.shape, bool)
    for a, (i, j) in enumerate(((0, 1), (1, 1), (1, 0), (1, -1))):
        ahead, behind = p[1 + i : p.shape[0] - 1 + i, 1 + j : p.shape[1] - 1 + j], p[1 - i : p.shape[0] - 1 - i, 1 - j : p.shape[1] - 1 - j]
        keep |= (angle == a) & (size >= ahead) & (size >= behind)
    weak, strong = keep & (size >= low), keep & (size >= high)
    while True:
        q = np.pad(strong, 1)
        grown = weak & np.logical_or.reduce([q[i : i + size.shape[0], j : j + size.shape[1]] for i in range(3) for j in range(3)])
        if (grown | strong).sum() == strong.sum():
            return np.repeat((strong * 255.0).astype(np.float32)[:, :, None], raster.shape[2], axis=2)
        strong = grown | strong


def scrambled(raster: np.ndarray, n: int, seed: int, image: int, scope: str = "image", remainder: str = "keep") -> np.ndarray:
    """Whole n x n blocks in seeded random order; a margin that holds no whole block stays (`keep`), is cropped, or is
    avoided by resizing to the nearest multiple of n."""
    if remainder == "resize":
        wide = max(1, round(raster.shape[0] / n)) * n
        at = np.arange(wide) * raster.shape[0] // wide
        raster = raster[at][:, at]
    side = raster.shape[0] // n * n
    if side == 0 or side == n:
        return raster.copy()
    per = side // n
    order = generator(seed, image if scope == "image" else 0, f"scramble:{n}").permutation(per * per)
    blocks = raster[:side, :side].reshape(per, n, per, n, -1).swapaxes(1, 2).reshape(per * per, n, n, -1)
    moved = blocks[order].reshape(per, per, n, n, -1).swapaxes(1, 2).reshape(side, side, -1)
    if remainder == "crop":
        return moved
    out = raster.copy()
    out[:side, :side] = moved
    return out


def apply(spec: str, text: str, raster: np.ndarray, seed: int, image: int, fill: str = "mean") -> np.ndarray:
    """One transform by its name: identity, edges, blur, scramble:<n>, remove:<cue>, random:<cue>."""
    family, _, what = spec.partition(":")
    if family == "identity":
        return raster
    if family == "edges":
        return edges(raster)
    if family == "blur":
        return blurred(raster)
    if family == "scramble":
        return scrambled(raster, int(what), seed, image)
    mask = cue_mask(text, what)
    return inpainted(raster, mask if family == "remove" else random_mask(mask, seed, image, what), fill)


TRANSFORMS = ("identity", "edges", "blur", "scramble:4", "scramble:8", "scramble:16", *(f"{f}:{c}" for c in CUES for f in ("remove", "random")))
