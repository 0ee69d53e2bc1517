"""Documents as clouds in the form that trainings store: of every voxel of the augmented cloud the pixel that the tokeniser keeps, as its
place, its code point and its depth. A third of the bytes of six doubles a point, and the same points come back; NumPy only."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa

from pointloom.functions.fixed import PRIME, draw_of
from pointloom.operators import augment
from pointloom.operators.corpora import image_colours, raster_shape

#: Scaling and shifting of pre-training, as published.
RHO, TAU = 0.5, 0.5
#: Columns of the stored form; ``n`` is the number of pixels of the whole image.
COLUMNS = ("n", "rho", "tau", "at", "cp", "depth")
SCHEMA = "n int, rho double, tau double, at array<int>, cp array<int>, depth array<double>"


def augmented(pts: np.ndarray, sample: int, seed: int = 3, rho: float = RHO, tau: float = TAU) -> np.ndarray:
    """A cloud turned about the upright axis by an angle of its own and brought back into the cube, scaled, shifted, and with
    standardised colours; the draws are those of :mod:`pointloom.operators.augment`."""
    u = draws(sample, seed)
    colours = [(pts[:, 3 + c] - augment.MEAN[c]) / augment.STD[c] for c in range(3)]
    return np.stack([*moved(turned(*pts[:, :3].T, u), u, rho, tau), *colours], 1)


def draws(sample: int, seed: int = 3) -> list[float]:
    return [float(draw_of(seed + k, sample)) / PRIME for k in range(5)]


def turned(x: np.ndarray, y: np.ndarray, z: np.ndarray, u: list[float]) -> list[np.ndarray]:
    turn, dx, dy = 2 * math.pi * u[0], x - 0.5, y - 0.5
    return [(math.cos(turn) * dx - math.sin(turn) * dy) / math.sqrt(2) + 0.5, (math.sin(turn) * dx + math.cos(turn) * dy) / math.sqrt(2) + 0.5, z]


def moved(axes: list[np.ndarray], u: list[float], rho: float, tau: float) -> list[np.ndarray]:
    factor = rho + (1 - rho) * u[1]
    return [c * factor + v * min(1 - factor, tau) for c, v in zip(axes, u[2:], strict=True)]


def code_points(text: str | None) -> np.ndarray:
    return np.frombuffer((text or "").encode("utf-32-le"), np.int32)


#: Standardised colours by code point; what stands from 255 on is white.
_COLOURS = [(c - m) / s for c, m, s in zip(image_colours(np.arange(256)), augment.MEAN, augment.STD, strict=True)]


def kept(samples, texts, teacher, rows_of, moves=((RHO, TAU),)) -> list[list[pa.Array]]:
    """Of every (rho, tau) of ``moves`` the columns of :data:`COLUMNS` for some documents, which are lifted and turned once for all of
    them; ``rows_of(columns)`` numbers the points to keep."""
    sizes, out = [], [[[] for _ in range(3)] for _ in moves]
    for sample, text in zip(samples, texts, strict=True):
        cps, u = code_points(text), draws(sample)
        sizes.append(len(cps))
        (x, y, z), low = places(len(cps), teacher(cps) if len(cps) else np.zeros(0)), np.minimum(cps, 255)
        axes, colours = turned(x, y, z, u), [c[low] for c in _COLOURS]
        for own, (rho, tau) in zip(out, moves, strict=True):
            at = rows_of([*moved(axes, u, rho, tau), *colours]).astype(np.int32)
            for values, column in zip(own, (at, cps[at], y[at]), strict=True):
                values.append(column)
    types = (pa.int32(), pa.int32(), pa.float64())
    return [[pa.array(sizes, pa.int32()), *[pa.array(np.full(len(sizes), v)) for v in move], *[_lists(v, t) for v, t in zip(own, types, strict=True)]] for own, move in zip(out, moves, strict=True)]


def places(n: int, depth: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Coordinates of the pixels of an image, as :func:`~pointloom.operators.lift.lifted` has them."""
    h, w = raster_shape(n)
    # a row and a column at a time
    x, z = (np.arange(w) + 0.5) / max(1, w), 1 - (np.arange(h) + 0.5) / max(1, h)
    return np.tile(x, h)[:n], depth, np.repeat(z, w)[:n]


def _lists(arrays: list[np.ndarray], kind) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, arrays)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(arrays) if arrays else [], kind))


def turns(samples: np.ndarray, rho: np.ndarray, tau: np.ndarray, seed: int = 3) -> list[np.ndarray]:
    """Of every sample what :func:`augmented` draws: cosine and sine of its turn, its factor, and its shift along each axis."""
    u = [draw_of(seed + k, samples) / PRIME for k in range(5)]
    angle = (2 * math.pi * u[0]).tolist()
    factor = rho + (1 - rho) * u[1]
    return [np.array([math.cos(x) for x in angle]), np.array([math.sin(x) for x in angle]), factor, *[v * np.minimum(1 - factor, tau) for v in u[2:]]]


def points(samples: np.ndarray, n: np.ndarray, rho: np.ndarray, tau: np.ndarray, sizes: np.ndarray, at: np.ndarray, cp: np.ndarray, depth: np.ndarray) -> np.ndarray:
    """The kept points of some documents, one after the other, as their augmented clouds have them; ``sizes``: points of each."""
    shapes = np.array([raster_shape(k) for k in n.tolist()]).reshape(-1, 2)
    cos, sin, factor, *shift = (np.repeat(v, sizes) for v in turns(samples, rho, tau))
    h, w = (np.repeat(v, sizes) for v in shapes.T)
    dx, dy = (at % w + 0.5) / w - 0.5, depth - 0.5
    out = np.empty((len(at), 6))
    out[:, 0] = ((cos * dx - sin * dy) / math.sqrt(2) + 0.5) * factor + shift[0]
    out[:, 1] = ((sin * dx + cos * dy) / math.sqrt(2) + 0.5) * factor + shift[1]
    out[:, 2] = (1 - (at // w + 0.5) / h) * factor + shift[2]
    for c, colour in enumerate(image_colours(cp)):
        out[:, 3 + c] = (colour - augment.MEAN[c]) / augment.STD[c]
    return out
