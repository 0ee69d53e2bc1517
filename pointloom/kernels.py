"""NumPy kernels on packed clouds; no Spark here."""

from __future__ import annotations

import numpy as np

from pointloom.operators.baselines import net_weight
from pointloom.operators.embed import closed_form_array, token_sums
from pointloom.schema import GridSpec

_BANKS: dict = {}
#: Clouds below so many points go through the centre kernel many at a time, in blocks of so many points; larger ones by themselves.
BATCH_POINTS, BLOCK_POINTS = 4096, 1 << 15
#: Coordinates of places in a block that hold no point; squares of their distances are finite.
NOWHERE = 1e150


def voxelise_packed(pts: np.ndarray, grid: GridSpec):
    """(n, 6) points, numbered by position -> voxel keys (m, 3) and representatives (m, 6): largest sum of attributes, ties
    to the larger number, as the DataFrame operator has it."""
    key = np.clip(np.floor(pts[:, :3] / grid.edge), 0, grid.size - 1).astype(np.int64)
    flat = (key[:, 0] * 1024 + key[:, 1]) * 1024 + key[:, 2]
    score = np.floor((pts[:, 0] + pts[:, 1] + pts[:, 2] + pts[:, 3] + pts[:, 4] + pts[:, 5]) * 1000000 + 0.5)
    bits = len(pts).bit_length()
    if bits <= 30 and score.min() >= 0 and score.max() < 1 << 23 and grid.size**3 << (23 + bits) < 1 << 63:
        # voxel, score and number fit one integer, and integers are sorted much faster than rows
        packed = ((key[:, 0] * grid.size + key[:, 1]) * grid.size + key[:, 2]) << (23 + bits) | score.astype(np.int64) << bits | np.arange(len(pts))
        packed.sort()
        voxel = packed >> (23 + bits)
        at = packed[np.concatenate((voxel[1:] != voxel[:-1], [True]))] & ((1 << bits) - 1)
    else:
        order = np.lexsort((-np.arange(len(pts)), -score, flat))
        at = order[np.concatenate(([True], np.diff(flat[order]) != 0))]
    return key[at], pts[at]


def packed_tokens(pts: np.ndarray, grid: GridSpec, channels: int = 4, features: str = "graph"):
    """Voxels a patch and exact token numerators of one cloud."""
    return packed_patches(pts, grid, channels, features)[1:]


def packed_patches(pts: np.ndarray, grid: GridSpec, channels: int = 4, features: str = "graph"):
    """Cells (p, 3), voxels a patch and exact token numerators (p, C) of one cloud."""
    a = grid.patch
    if not len(pts):
        return np.zeros((0, 3), np.int64), np.zeros(0, np.int64), np.zeros((0, channels), np.int64)
    key, rep = voxelise_packed(pts, grid)
    cell, slot = key // a, key % a @ np.array([1, a, a * a])
    patch = (cell[:, 0] * 1024 + cell[:, 1]) * 1024 + cell[:, 2]
    order = np.argsort(patch, kind="stable")
    fx = np.floor(rep * 1000000 + 0.5).astype(np.int64)
    name = (a, channels, features)
    if name not in _BANKS:
        _BANKS[name] = closed_form_array(a, 12 if features == "graph" else 6, channels)
    patch = patch[order]
    first = np.concatenate(([True], patch[1:] != patch[:-1]))
    return cell[order[first]], *token_sums(fx[order], slot[order], patch, _BANKS[name], features)


def centre_groups(xyz: np.ndarray, n: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Of a cloud's coordinates (3, size): positions of ``n`` centres as :func:`~pointloom.operators.baselines.fps_kernel` picks them, and
    (n, k) of the nearest points of each, in no order; ties go to the earlier point in both. Distances are computed once for both.

    A new centre is as far from the centres before it as any point. Where the third coordinate runs one way through the cloud (the rows of
    an image), points farther from the centre than that along this axis change no later pick and are not looked at. Neighbours are first
    looked for within a guess, as far as a centre before needed; where it was too small, among all points.
    """
    size = xyz.shape[1]
    n, k = min(n, size), min(k, size)
    taken, groups = np.zeros(n, np.int64), np.zeros((n, k), np.int64)
    near, room, last = np.full(size, np.inf), np.empty((3, size)), xyz[2]
    axis = -last if (last[1:] <= last[:-1]).all() else last if (last[1:] >= last[:-1]).all() else None
    at, reach, guess = 0, np.inf, np.inf
    for j in range(n):
        taken[j] = at
        lo, left, right, hi, most = 0, 0, size, size, guess
        if axis is not None and reach < np.inf:
            most = min(guess, reach)
            # wider than needed by more than any rounding
            far, close = reach**0.5 * (1 + 1e-6) + 1e-12, most**0.5 * (1 + 1e-6) + 1e-12
            z = axis[at]
            lo, left, right, hi = axis.searchsorted((z - far, z - close, z + close, z + far)).tolist()
        e = room[:, : hi - lo]
        np.subtract(xyz[:, lo:hi], xyz[:, at : at + 1], out=e)
        np.multiply(e, e, out=e)
        d = e[0]
        d += e[1]
        d += e[2]
        held = near[lo:hi]
        np.minimum(held, d, out=held)
        found = (d[left - lo : right - lo] <= most).nonzero()[0]
        if len(found) >= k:
            found += left - lo
        else:
            e = xyz - xyz[:, at : at + 1]
            e *= e
            d = e[0] + e[1] + e[2]
            lo, found = 0, np.arange(size)
        values = d[found]
        if len(found) > k:
            bound = np.partition(values, k - 1)[k - 1]
            inside = values <= bound
            found, values = found[inside], values[inside]
            if len(found) > k:
                found = found[values.argsort(kind="stable")[:k]]
            guess = max(bound, guess if guess < np.inf else 0.0)
        groups[j] = found + lo
        at = int(near.argmax())
        reach = float(near[at])
    return taken, groups


def centre_groups_block(xyz: np.ndarray, sizes: np.ndarray, n: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """:func:`centre_groups` of many clouds at once, (3, clouds, places) with :data:`NOWHERE` after a cloud's ``sizes`` points: (n, clouds)
    and (n, clouds, k). Ranks beyond a cloud's size mean nothing; a cloud of fewer than k points has its last one again and again."""
    many, places = xyz.shape[1:]
    k, row = min(k, places), np.arange(many)
    taken, groups = np.zeros((n, many), np.int64), np.empty((n, many, k), np.int64)
    groups[:] = np.minimum(np.arange(k), sizes[:, None] - 1)
    full = np.flatnonzero(sizes > k)
    near = np.where(np.arange(places) < sizes[:, None], np.inf, -np.inf)
    e, at = np.empty_like(xyz), np.zeros(many, np.int64)
    for j in range(n):
        taken[j] = at
        np.subtract(xyz, xyz[:, row, at][:, :, None], out=e)
        np.multiply(e, e, out=e)
        d = e[0]
        d += e[1]
        d += e[2]
        np.minimum(near, d, out=near)
        at = near.argmax(axis=1)
        if len(full):
            own = d if len(full) == many else d[full]
            bound = np.partition(own, k - 1, axis=1)[:, k - 1 : k]
            inside = own <= bound
            count = np.count_nonzero(inside, axis=1)
            for r in np.flatnonzero(count > k).tolist():
                # of those as near as the k-th, the earlier ones
                inside[r, np.flatnonzero(own[r] == bound[r])[k - count[r] :]] = False
            groups[j, full] = np.flatnonzero(inside).reshape(len(full), k) - np.arange(len(full))[:, None] * places
    return taken, groups


def centre_tokens(clouds: list[np.ndarray], n: int, k: int, hidden: int = 4, out: int = 3) -> list[np.ndarray]:
    """Tokens (ranks, out) of the centres of clouds (3, size) in the order of their ranks:
    :func:`~pointloom.operators.baselines.mini_pointnet` on arrays. All its numbers are whole and below 2**53, so products of doubles are exact."""
    weights = lambda layer, i, o: np.array([[net_weight(layer, a, b) for a in range(i)] for b in range(o)], np.float64)
    one, two = weights(1, 3, hidden), weights(2, 2 * hidden, out)

    def network(xyz, taken, groups):
        # (3, points), (groups,) and (k, groups) -> (out, groups); the first layer has no constant, so it is applied to points instead of offsets
        first = one @ np.floor(xyz * 1000000 + 0.5)
        h = np.maximum(first[:, groups] - first[:, None, taken], 0)
        own = (two[:, :hidden] @ h.reshape(hidden, -1)).reshape(out, *h.shape[1:]).max(axis=1)
        return np.maximum(own + two[:, hidden:] @ h.max(axis=1), 0).astype(np.int64)

    tokens: list = [np.zeros((0, out), np.int64)] * len(clouds)
    order = sorted((c for c in range(len(clouds)) if clouds[c].shape[1]), key=lambda c: clouds[c].shape[1])
    lo = 0
    while lo < len(order):
        hi = lo + 1
        while hi < len(order) and (places := clouds[order[hi]].shape[1]) < BATCH_POINTS and (hi + 1 - lo) * places <= BLOCK_POINTS:
            hi += 1
        some, lo = order[lo:hi], hi
        if len(some) == 1:
            taken, groups = centre_groups(clouds[some[0]], n, k)
            tokens[some[0]] = network(clouds[some[0]], taken, groups.T).T
            continue
        sizes = np.array([clouds[c].shape[1] for c in some])
        xyz = np.full((3, len(some), sizes[-1]), NOWHERE)
        for r, c in enumerate(some):
            xyz[:, r, : sizes[r]] = clouds[c]
        taken, groups = centre_groups_block(xyz, sizes, min(n, sizes[-1]), k)
        start = np.arange(len(some)) * sizes[-1]
        made = network(xyz.reshape(3, -1), (taken + start).ravel(), (groups + start[:, None]).reshape(taken.size, -1).T).reshape(out, *taken.shape)
        for r, c in enumerate(some):
            tokens[c] = made[:, : sizes[r], r].T
    return tokens
