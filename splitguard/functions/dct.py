"""Integer cosine transform, threshold rules and the algebra of orientations.

Everything is exact: the basis is rounded once to integers, rasters are integers, and
products stay below 2 ** 53, so float64 matrix products give the true integers.

A block is a square of low-frequency coefficients, coefficient p = side * u + v with u the
vertical and v the horizontal frequency. Bit p of a fingerprint has weight 2 ** p; 64 bits are
held as a signed long.
"""

from __future__ import annotations

import math

import numpy as np

SIDE = 32
SCALE = 8192
DEPTH = 16
#: basis[u][x], u < 16, x < 32. No entry is near a rounding tie, so all platforms agree.
BASIS = np.array(
    [
        [round(SCALE * math.cos((2 * x + 1) * u * math.pi / (2 * SIDE))) for x in range(SIDE)]
        for u in range(DEPTH)
    ],
    np.int64,
)
#: Largest cell for which a transform of 32 x 32 cells stays exact.
MOST_CELL = (1 << 53) // (SCALE * SCALE * SIDE * SIDE)

THRESHOLDS = ("mean_all", "mean_ac", "median_all", "sign_ac")
PAPER_OPS = ("id", "r90", "r180", "r270", "flip_lr", "flip_tb")
ALL_OPS = (*PAPER_OPS, "transpose", "anti")

# op -> (transposed first, sign by u, sign by v)
_ALGEBRA = {
    "id": (False, False, False),
    "r90": (True, True, False),
    "r180": (False, True, True),
    "r270": (True, False, True),
    "flip_lr": (False, False, True),
    "flip_tb": (False, True, False),
    "transpose": (True, False, False),
    "anti": (True, True, True),
}


def orientation_tables(op: str, side: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """(source, sign): coefficient p of the reoriented raster is sign[p] * block[source[p]]."""
    transposed, by_u, by_v = _ALGEBRA[op]
    u, v = np.divmod(np.arange(side * side), side)
    source = v * side + u if transposed else u * side + v
    sign = np.where(by_u & (u % 2 == 1), -1, 1) * np.where(by_v & (v % 2 == 1), -1, 1)
    return source, sign


def pixel_source(op: str, side: int = SIDE) -> np.ndarray:
    """Index of the cell that stands at each cell of a square raster after op."""
    cells = np.arange(side * side).reshape(side, side)
    turned = {
        "id": cells,
        "r90": np.rot90(cells, 1),
        "r180": np.rot90(cells, 2),
        "r270": np.rot90(cells, 3),
        "flip_lr": cells[:, ::-1],
        "flip_tb": cells[::-1],
        "transpose": cells.T,
        "anti": np.rot90(cells, 2).T,
    }
    return turned[op].ravel()


def blocks_of(rasters: np.ndarray, side: int = 8, ortho: bool = False) -> np.ndarray:
    """(n, side * side) integer coefficients of (n, 32, 32) rasters.

    ortho scales the DC row and column by one over the square root of two, as 12 to 17.
    """
    if len(rasters) and (rasters.min() < 0 or rasters.max() > MOST_CELL):
        raise ValueError(f"cells must lie in 0..{MOST_CELL}")
    k = BASIS[:side].astype(float)
    out = np.rint(k @ rasters.astype(float) @ k.T).astype(np.int64)
    if ortho:
        out = out * np.outer(ortho_weights(side), ortho_weights(side))
    return out.reshape(len(rasters), side * side)


def ortho_weights(side: int) -> np.ndarray:
    weights = np.full(side, 17, np.int64)
    weights[0] = 12
    return weights


def size_basis(n: int, side: int = 8) -> np.ndarray:
    """basis[u][x] for n cells a side."""
    x, u = np.arange(n), np.arange(side)[:, None]
    return np.rint(SCALE * np.cos((2 * x + 1) * u * math.pi / (2 * n))).astype(np.int64)


def factor_blocks(grey: np.ndarray, factor: int, side: int = 8) -> np.ndarray:
    """(n, side * side) low coefficients of (n, height, width) rasters, each downsampled by a factor
    and transformed whole."""
    count, high, wide = grey.shape[0], grey.shape[1] // factor, grey.shape[2] // factor
    boxes = grey[:, : high * factor, : wide * factor].astype(np.int64)
    boxes = boxes.reshape(count, high, factor, wide, factor).sum(axis=(2, 4))
    return (size_basis(high, side) @ boxes @ size_basis(wide, side).T).reshape(count, side * side)


def factor_block(grey: np.ndarray, factor: int, side: int = 8) -> np.ndarray:
    """factor_blocks of one raster."""
    return factor_blocks(grey[None], factor, side)[0]


def bits_of(blocks: np.ndarray, threshold: str) -> np.ndarray:
    """(n, bits) booleans: coefficient strictly over the threshold."""
    count = blocks.shape[1]
    if threshold == "mean_all":
        return count * blocks > blocks.sum(axis=1, keepdims=True)
    if threshold == "mean_ac":
        bits = (count - 1) * blocks > blocks[:, 1:].sum(axis=1, keepdims=True)
    elif threshold == "median_all":
        ranked = np.sort(blocks, axis=1)
        return 2 * blocks > (ranked[:, count // 2 - 1] + ranked[:, count // 2])[:, None]
    elif threshold == "sign_ac":
        bits = blocks > 0
    else:
        raise ValueError(f"threshold must be one of {THRESHOLDS}")
    bits[:, 0] = False
    return bits


def words_of(bits: np.ndarray) -> np.ndarray:
    """(n, words) signed longs of (n, bits); the last word is padded with zeros."""
    n, count = bits.shape
    padded = np.zeros((n, -(-count // 64) * 64), np.uint8)
    padded[:, :count] = bits
    return np.packbits(padded, axis=1, bitorder="little").view("<i8")


def oriented(blocks: np.ndarray, op: str) -> np.ndarray:
    source, sign = orientation_tables(op, math.isqrt(blocks.shape[1]))
    return blocks[:, source] * sign


def average_bits(rasters: np.ndarray, side: int = 8) -> np.ndarray:
    """Box means of the raster over their global mean; cells are compared as sums."""
    step = rasters.shape[1] // side
    cells = rasters.reshape(len(rasters), side, step, side, step).sum(axis=(2, 4))
    cells = cells.reshape(len(rasters), side * side).astype(np.int64)
    return side * side * cells > cells.sum(axis=1, keepdims=True)
