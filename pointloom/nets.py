"""Small transformers over ragged voxel tokens in NumPy, with reverse-mode gradients; no Spark here."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from pointloom.functions.fixed import draw_of
from pointloom.operators.baselines import fps_kernel, nearest_kernel

# reverse mode ----------------------------------------------------------------------------------------------------


class Var:
    """An array that remembers how it was made; ``backward`` fills ``grad`` of the leaves it came from, once. What is made of
    ``fixed`` arrays alone is fixed: it remembers nothing, and no gradient is worked out for it."""

    __slots__ = ("value", "grad", "made_from", "fixed")

    def __init__(self, value, made_from=(), fixed=False):
        self.value, self.grad, self.made_from = np.asarray(value), None, tuple(x for x in made_from if not x[0].fixed)
        self.fixed = fixed or (bool(made_from) and not self.made_from)

    def backward(self) -> None:
        order, seen, stack = [], set(), [(self, False)]
        while stack:
            v, done = stack.pop()
            if done:
                order.append(v)
            elif id(v) not in seen:
                seen.add(id(v))
                stack.append((v, True))
                stack += [(p, False) for p, _ in v.made_from]
        self.grad = np.ones_like(self.value)
        while order:
            v = order.pop()
            # zeros, as before the first step of a head of zeros, have nothing but zeros behind them
            if v.grad is not None and (v.grad.flat[:1].any() or v.grad.any()):
                for p, back in v.made_from:
                    g = back(v.grad)
                    p.grad = g if p.grad is None else p.grad + g
            if v.made_from:
                # what lies behind is done with: only the leaves keep their gradient
                v.grad, v.made_from = None, ()


def _fit(g, shape):
    """Sum a gradient over the axes that broadcasting added."""
    if g.ndim > len(shape):
        # rows are added up as one product
        wide = g.shape[g.ndim - len(shape) :]
        flat = g.reshape(-1, math.prod(wide))
        g = (np.ones(len(flat), g.dtype) @ flat).reshape(wide)
    for k, n in enumerate(shape):
        if n == 1 and g.shape[k] != 1:
            g = g.sum(axis=k, keepdims=True)
    return g


def add(a: Var, b: Var) -> Var:
    return Var(a.value + b.value, ((a, lambda g: _fit(g, a.value.shape)), (b, lambda g: _fit(g, b.value.shape))))


def mul(a: Var, b: Var) -> Var:
    return Var(a.value * b.value, ((a, lambda g: _fit(g * b.value, a.value.shape)), (b, lambda g: _fit(g * a.value, b.value.shape))))


def scale(a: Var, k) -> Var:
    return Var(a.value * k, ((a, lambda g: _fit(g * k, a.value.shape)),))


def matmul(a: Var, b: Var) -> Var:
    if b.value.ndim == 2 and a.value.ndim > 2:
        # one product of all rows, not one a sample
        return shape(matmul(shape(a, (-1, a.value.shape[-1])), b), (*a.value.shape[:-1], b.value.shape[1]))

    def back_b(g):
        return _fit(np.swapaxes(a.value, -1, -2) @ g, b.value.shape)

    return Var(a.value @ b.value, ((a, lambda g: _fit(g @ np.swapaxes(b.value, -1, -2), a.value.shape)), (b, back_b)))


def move(a: Var, axes) -> Var:
    return Var(a.value.transpose(axes), ((a, lambda g: g.transpose(np.argsort(axes))),))


def shape(a: Var, dims) -> Var:
    return Var(a.value.reshape(dims), ((a, lambda g: g.reshape(a.value.shape)),))


def sum_by(values: np.ndarray, group: np.ndarray, n: int) -> np.ndarray:
    """Sums of the rows of each group."""
    out = np.zeros((n, *values.shape[1:]), values.dtype)
    if len(group):
        if (group[1:] < group[:-1]).any():
            order = np.argsort(group, kind="stable")
            values, group = values[order], group[order]
        at = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
        out[group[at]] = np.add.reduceat(values, at, axis=0)
    return out


def take(a: Var, index) -> Var:
    """Rows of ``a`` by number; repeated rows add up their gradients."""
    return Var(a.value[index], ((a, lambda g: sum_by(g, np.asarray(index), len(a.value))),))


def slot_linear(x: Var, w: Var, slot: np.ndarray) -> Var:
    """Each row times the matrix of its slot: rows are handled slot by slot, so no matrix is copied a row."""
    order = np.argsort(slot, kind="stable")
    of = slot[order]
    cuts = np.flatnonzero(np.concatenate(([True], of[1:] != of[:-1]))) if len(of) else np.zeros(0, np.int64)
    groups = list(zip(of[cuts].tolist(), cuts.tolist(), np.append(cuts, len(of))[1:].tolist(), strict=True))
    # rows stand by slot once, so that a slot's rows are a slice
    rows = x.value[order]
    out = np.empty((len(of), w.value.shape[2]), np.result_type(rows, w.value))
    for s, lo, hi in groups:
        np.matmul(rows[lo:hi], w.value[s], out=out[lo:hi])

    def unsorted(v):
        back = np.empty_like(v)
        back[order] = v
        return back

    def back_x(g):
        g, d = g[order], np.empty(rows.shape, g.dtype)
        for s, lo, hi in groups:
            np.matmul(g[lo:hi], w.value[s].T, out=d[lo:hi])
        return unsorted(d)

    def back_w(g):
        g, d = g[order], np.zeros_like(w.value)
        for s, lo, hi in groups:
            d[s] = rows[lo:hi].T @ g[lo:hi]
        return d

    return Var(unsorted(out), ((x, back_x), (w, back_w)))


def put(a: Var, index, rows: int) -> Var:
    """Rows of ``a`` written to the numbered rows of a zero array."""
    out = np.zeros((rows, *a.value.shape[1:]), a.value.dtype)
    out[index] = a.value
    return Var(out, ((a, lambda g: g[index]),))


def at_places(a: Var, places: np.ndarray) -> Var:
    """Rows of ``a`` by numbers of which none is repeated."""

    def back(g):
        out = np.zeros_like(a.value)
        out[places] = g
        return out

    return Var(a.value[places], ((a, back),))


def columns(a: Var, lo: int, hi: int) -> Var:
    """The last axis from ``lo`` to ``hi``."""

    def back(g):
        out = np.zeros_like(a.value)
        out[..., lo:hi] = g
        return out

    return Var(a.value[..., lo:hi], ((a, back),))


def stack_rows(parts: list[Var]) -> Var:
    cuts = np.cumsum([0] + [len(p.value) for p in parts])
    return Var(np.concatenate([p.value for p in parts]), tuple((p, lambda g, a=a, b=b: g[a:b]) for p, a, b in zip(parts, cuts[:-1], cuts[1:], strict=True)))


def mean_by(a: Var, group: np.ndarray, n: int) -> Var:
    count = np.bincount(group, minlength=n).astype(a.value.dtype)
    out = sum_by(a.value, group, n)
    w = 1 / np.maximum(count, 1)
    return Var(out * w.reshape(-1, *[1] * (out.ndim - 1)), ((a, lambda g: (g * w.reshape(-1, *[1] * (g.ndim - 1)))[group]),))


def max_by(a: Var, group: np.ndarray, n: int) -> Var:
    """Largest of each column in each group; the gradient goes to the first largest row."""
    out = np.full((n, a.value.shape[1]), -np.inf, a.value.dtype)
    order = np.argsort(group, kind="stable") if (group[1:] < group[:-1]).any() else None
    values, of = (a.value, group) if order is None else (a.value[order], group[order])
    at = np.flatnonzero(np.concatenate(([True], of[1:] != of[:-1]))) if len(of) else np.zeros(0, np.int64)
    filled = of[at]
    if len(at):
        k = len(of) // len(at)
        if k * len(at) == len(of) and (np.diff(at) == k).all():
            # groups of one size, as neighbours are: one comparison a place, over all groups
            best, first = values[at], np.repeat(at[:, None], values.shape[1], 1)
            for j in range(1, k):
                other = values[j::k]
                more = other > best
                np.copyto(best, other, where=more)
                np.copyto(first, (at + j)[:, None], where=more)
            out[filled] = best
        else:
            out[filled] = np.maximum.reduceat(values, at, axis=0)
            first = np.minimum.reduceat(np.where(values == out[of], np.arange(len(of))[:, None], len(of) - 1), at, axis=0)
        first = first if order is None else order[first]

    def back(g):
        # groups share no row, so nothing is added up
        back_ = np.zeros_like(a.value)
        if len(at):
            back_[first, np.arange(g.shape[1])] = g[filled]
        return back_

    return Var(np.where(np.isfinite(out), out, 0.0), ((a, back),))


#: Groups that :func:`max_of` compares at a time.
BLOCK = 256


def max_of(a: Var, rows: np.ndarray, group: np.ndarray, n: int) -> Var:
    """:func:`max_by` of the numbered rows of ``a``, whose groups stand in order; a group without rows gives zeros."""
    out, first = np.zeros((n, a.value.shape[1]), a.value.dtype), np.zeros((n, a.value.shape[1]), np.int64)
    at = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1]))) if len(group) else np.zeros(0, np.int64)
    filled, sizes = group[at], np.diff(np.append(at, len(group)))
    for lo in range(0, len(at), BLOCK):
        start, size = at[lo : lo + BLOCK], sizes[lo : lo + BLOCK]
        best, which = a.value[rows[start]], np.repeat(rows[start][:, None], out.shape[1], 1)
        for j in range(1, int(size.max())):
            # one comparison a place, over all groups; those that have no such place compare their last row again
            row = rows[start + np.minimum(j, size - 1)]
            other = a.value[row]
            more = other > best
            np.copyto(best, other, where=more)
            np.copyto(which, row[:, None], where=more)
        out[filled[lo : lo + BLOCK]], first[filled[lo : lo + BLOCK]] = best, which

    def back(g):
        there = first[filled] * g.shape[1] + np.arange(g.shape[1])
        return np.bincount(there.ravel(), g[filled].ravel(), a.value.size).astype(g.dtype, copy=False).reshape(a.value.shape)

    return Var(out, ((a, back),))


def gelu(a: Var) -> Var:
    k = math.sqrt(2 / math.pi)
    x = a.value
    # products: NumPy's third power goes through the general one, many times slower
    t = x * x
    t *= 0.044715 * k
    t += k
    t *= x
    np.tanh(t, out=t)

    def back(g):
        square = x * x
        d = 1 - t * t
        d *= x
        square *= 3 * 0.044715 * k
        square += k
        d *= square
        d += t
        d += 1
        d *= 0.5
        d *= g
        return d

    out = 1 + t
    out *= x
    out *= 0.5
    return Var(out, ((a, back),))


def relu(a: Var) -> Var:
    return Var(np.maximum(a.value, 0), ((a, lambda g: g * (a.value > 0)),))


def layer_norm(a: Var, gain: Var, bias: Var, eps: float = 1e-6) -> Var:
    # sums of a short last axis are products with a vector, which go many times faster
    each = np.full((a.value.shape[-1], 1), 1 / a.value.shape[-1], a.value.dtype)
    z = a.value - a.value @ each
    inv = 1 / np.sqrt((z * z) @ each + eps)
    z *= inv

    def back(g):
        dz = g * gain.value
        far = (dz * z) @ each
        dz -= dz @ each
        dz -= z * far
        dz *= inv
        return dz

    return Var(z * gain.value + bias.value, ((a, back), (gain, lambda g: _fit(g * z, gain.value.shape)), (bias, lambda g: _fit(g, bias.value.shape))))


def softmax(a: Var, mask=None) -> Var:
    p = a.value.copy() if mask is None else np.where(mask, a.value, -1e30)
    p -= p.max(-1, keepdims=True)
    np.exp(p, out=p)
    p /= p.sum(-1, keepdims=True)

    def back(g):
        d = g * p
        d -= p * d.sum(-1, keepdims=True)
        return d

    return Var(p, ((a, back),))


def total(a: Var) -> Var:
    return Var(a.value.sum(), ((a, lambda g: np.broadcast_to(g, a.value.shape)),))


def beside(a: Var, b: Var) -> Var:
    """The columns of both."""
    w = a.value.shape[1]
    return Var(np.concatenate([a.value, b.value], 1), ((a, lambda g: g[:, :w]), (b, lambda g: g[:, w:])))


# model -----------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class ModelConfig:
    """Sizes of tokeniser, encoder and decoder."""

    blocks: int = 2
    width: int = 32
    heads: int = 4
    decoder_blocks: int = 1
    decoder_width: int = 32
    decoder_heads: int = 4
    grid: int = 16
    patch: int = 4
    features: str = "graph"
    group: int = 0  #: points a group of the fixed-token tokeniser; 0: voxel tokens

    @property
    def n_features(self) -> int:
        return 12 if self.features == "graph" else 6

    @property
    def slots(self) -> int:
        return self.patch**3

    def shapes(self) -> dict[str, tuple[int, ...]]:
        c, d = self.width, self.decoder_width
        out = {"cls": (1, c), "mask": (1, d), "adapt.w": (c, d), "adapt.b": (d,)}
        for side, w in (("enc", c), ("dec", d)):
            out |= {f"{side}.pos1.w": (3, w), f"{side}.pos1.b": (w,), f"{side}.pos2.w": (w, w), f"{side}.pos2.b": (w,), f"{side}.norm.g": (w,), f"{side}.norm.b": (w,)}
        if self.group:
            out |= {"group1.w": (3, c), "group1.b": (c,), "group2.w": (2 * c, c), "group2.b": (c,), "points.w": (d, 3 * self.group), "points.b": (3 * self.group,)}
        else:
            out |= {"slot.w": (self.slots, self.n_features, c), "head.w": (self.slots, d, 12), "head.b": (self.slots, 12), "occ.w": (d, self.slots), "occ.b": (self.slots,)}
        for side, n, w in (("enc", self.blocks, c), ("dec", self.decoder_blocks, d)):
            for k in range(n):
                p = f"{side}.{k}"
                out |= {f"{p}.n1.g": (w,), f"{p}.n1.b": (w,), f"{p}.qkv.w": (w, 3 * w), f"{p}.qkv.b": (3 * w,), f"{p}.out.w": (w, w), f"{p}.out.b": (w,)}
                out |= {f"{p}.n2.g": (w,), f"{p}.n2.b": (w,), f"{p}.up.w": (w, 4 * w), f"{p}.up.b": (4 * w,), f"{p}.down.w": (4 * w, w), f"{p}.down.b": (w,)}
        return out

    def n_params(self) -> int:
        return sum(math.prod(s) for s in self.shapes().values())


TINY = ModelConfig()
SMALL_TINY = ModelConfig(blocks=3, width=48)
S = ModelConfig(12, 384, 6, 8, 512, 16, 224, 16)
B = ModelConfig(12, 768, 12, 8, 512, 16, 224, 16)
L = ModelConfig(15, 768, 12, 8, 512, 16, 224, 16)


def init(cfg: ModelConfig, seed: int = 0) -> dict[str, np.ndarray]:
    rng, out = np.random.default_rng(seed), {}
    for name, dims in cfg.shapes().items():
        if name.endswith(".g"):
            out[name] = np.ones(dims)
        elif name.endswith(".b"):
            out[name] = np.zeros(dims)
        else:
            out[name] = rng.normal(0, 0.02 if name in ("cls", "mask") else math.sqrt(1 / dims[-2]) if len(dims) > 1 else 0.02, dims)
    return out


def linear(x: Var, p: dict[str, Var], name: str) -> Var:
    """One product of all rows, with the bias added in place."""
    w, b = p[f"{name}.w"], p[f"{name}.b"]
    flat = x.value.reshape(-1, x.value.shape[-1])
    out = flat @ w.value
    out += b.value
    rows = lambda g: g.reshape(len(flat), -1)
    back_x = lambda g: (rows(g) @ w.value.T).reshape(x.value.shape)
    return Var(out.reshape(*x.value.shape[:-1], out.shape[1]), ((x, back_x), (w, lambda g: flat.T @ rows(g)), (b, lambda g: _fit(rows(g), b.value.shape))))


def constant(x, like: Var) -> Var:
    """Data beside parameters: without a gradient, in their precision."""
    return Var(np.asarray(x).astype(like.value.dtype, copy=False), fixed=True)


@dataclass(frozen=True)
class Layout:
    """Rows of all samples stand one after the other without padding; only attention sees them side by side, padded to the longest."""

    place: np.ndarray  #: of each row in the padded array
    wide: int  #: places a sample
    mask: np.ndarray  #: (samples, wide), the real places

    def spread(self, rows: np.ndarray, parts: int, heads: int) -> np.ndarray:
        """(rows, parts * w) -> (parts, samples, heads, wide, w / heads), with zeros for padding."""
        grid = np.zeros((self.mask.size, rows.shape[1]), rows.dtype)
        grid[self.place] = rows
        return np.ascontiguousarray(grid.reshape(*self.mask.shape, parts, heads, -1).transpose(2, 0, 3, 1, 4))

    def gather(self, grid: np.ndarray) -> np.ndarray:
        """The way back."""
        return grid.transpose(1, 3, 0, 2, 4).reshape(self.mask.size, -1)[self.place]


def heads_mixed(asks: Var, held: Var, heads: int, ask: Layout, hold: Layout) -> Var:
    """Queries (rows, w), and keys and values (rows, 2w) of the same samples -> (rows of the queries, w), all heads at once, one step
    forward and one back; padding is never attended to."""
    (q,), (k, v) = ask.spread(asks.value, 1, heads), hold.spread(held.value, 2, heads)
    inner = q.shape[-1]
    q *= 1 / math.sqrt(inner)
    a = q @ k.swapaxes(-1, -2)
    if not hold.mask.all():
        a += np.where(hold.mask, 0, -1e30).astype(a.dtype)[:, None, None, :]
    # sums of a short last axis are products with a vector
    a -= a.max(-1, keepdims=True)
    np.exp(a, out=a)
    a *= 1 / (a @ np.ones((hold.wide, 1), a.dtype))
    out, done = a @ v, {}

    def both(g):
        # worked out once for the queries and for what they look at
        if not done:
            (g,) = ask.spread(g, 1, heads)
            d = np.empty((2, *v.shape), g.dtype)
            np.matmul(a.swapaxes(-1, -2), g, out=d[1])
            s = g @ v.swapaxes(-1, -2)
            s -= (g * out) @ np.ones((inner, 1), g.dtype)
            s *= a
            dq = s @ k
            dq *= 1 / math.sqrt(inner)
            np.matmul(s.swapaxes(-1, -2), q, out=d[0])
            done.update(asks=ask.gather(dq[None]), held=hold.gather(d))
        return done

    return Var(ask.gather(out[None]), ((asks, lambda g: both(g)["asks"]), (held, lambda g: both(g)["held"])))


def attention(x: Var, p: dict[str, Var], name: str, heads: int, hold: Layout, rows=None, ask: Layout | None = None) -> Var:
    """What the rows of ``x`` see of each other; with ``rows`` and their layout ``ask`` only these look, at all of them."""
    w, b, cut = p[f"{name}.qkv.w"], p[f"{name}.qkv.b"], x.value.shape[1]
    side = lambda lo, hi: {"s.w": columns(w, lo, hi), "s.b": columns(b, lo, hi)}
    asks = linear(x if rows is None else at_places(x, rows), side(0, cut), "s")
    return linear(heads_mixed(asks, linear(x, side(cut, 3 * cut), "s"), heads, ask or hold, hold), p, f"{name}.out")


def transformer(x: Var, p: dict[str, Var], side: str, blocks: int, heads: int, hold: Layout, rows=None, ask: Layout | None = None) -> Var:
    """Codes of all rows, or of ``rows`` alone: then the last block works out nothing but keys and values of the others."""
    for k in range(blocks):
        n, own = f"{side}.{k}", (rows, ask) if k + 1 == blocks else (None, None)
        seen = attention(layer_norm(x, p[f"{n}.n1.g"], p[f"{n}.n1.b"]), p, n, heads, hold, *own)
        x = add(x if own[0] is None else at_places(x, rows), seen)
        x = add(x, linear(gelu(linear(layer_norm(x, p[f"{n}.n2.g"], p[f"{n}.n2.b"]), p, f"{n}.up")), p, f"{n}.down"))
    return layer_norm(x, p[f"{side}.norm.g"], p[f"{side}.norm.b"])


def position(corner: np.ndarray, p: dict[str, Var], side: str) -> Var:
    return linear(gelu(linear(constant(corner, p[f"{side}.pos1.w"]), p, f"{side}.pos1")), p, f"{side}.pos2")


@dataclass
class Tokens:
    """Tokens of a batch: sample of each, position in [0, 1], and the voxels (or grouped points) they are made of."""

    sample: np.ndarray
    corner: np.ndarray
    owner: np.ndarray  #: token of each voxel or point
    slot: np.ndarray
    feat: np.ndarray  #: (m, 12) or (m, 6) voxel attributes; (m, 3) offsets for groups
    cell: np.ndarray  #: (t, 3) patch of each token; for groups its rank among the centres
    n: int  #: samples
    ids: np.ndarray | None = None  #: numbers of the samples in the corpus
    made: dict = field(default_factory=dict, repr=False)  #: what is made of the tokens once for all models

    def pick(self, keep: np.ndarray, voxels: bool = True) -> Tokens:
        """The tokens to keep, with their rows of the tables made so far; without ``voxels`` nothing else of their voxels."""
        of = (self.owner[:0], self.slot[:0], self.feat[:0])
        if voxels:
            v = keep[self.owner]
            of = ((np.cumsum(keep) - 1)[self.owner[v]], self.slot[v], self.feat[v])
        made = {} if voxels else {k: x[keep] for k, x in self.made.items() if k[0] == "table"}
        return Tokens(self.sample[keep], self.corner[keep], *of, self.cell[keep], self.n, self.ids, made)

    def table(self, cfg: ModelConfig, kind) -> np.ndarray:
        """(tokens, slots * features): the attributes of each token's voxels at their slots, over the number of its voxels."""
        key = ("table", cfg.slots, cfg.n_features, np.dtype(kind).str)
        if key not in self.made:
            out = np.zeros((len(self.sample) * cfg.slots, cfg.n_features), kind)
            share = 1 / np.maximum(np.bincount(self.owner, minlength=len(self.sample)), 1)
            out[self.owner * cfg.slots + self.slot] = self.feat[:, : cfg.n_features] * share[self.owner, None]
            self.made[key] = out.reshape(len(self.sample), cfg.slots * cfg.n_features)
        return self.made[key]


#: Widest table of a token's slots; where there are few slots, one product with all of them goes faster than one a slot.
TABLE = 1 << 10


def tabled(cfg: ModelConfig) -> bool:
    return not cfg.group and cfg.slots * 12 <= TABLE


def embed(t: Tokens, p: dict[str, Var], cfg: ModelConfig) -> Var:
    n = len(t.sample)
    if cfg.group:
        h = relu(linear(constant(t.feat, p["group1.w"]), p, "group1"))
        return max_by(linear(beside(h, take(max_by(h, t.owner, n), t.owner)), p, "group2"), t.owner, n)
    w = p["slot.w"]
    if tabled(cfg):
        return matmul(Var(t.table(cfg, w.value.dtype), fixed=True), shape(w, (-1, cfg.width)))
    return mean_by(slot_linear(constant(t.feat[:, : cfg.n_features], w), w, t.slot), t.owner, n)


def unembed(codes: Var, t: Tokens, p: dict[str, Var], cfg: ModelConfig) -> Var:
    """Of every voxel the 12 attributes that its token's code gives at its slot."""
    w, b = p["head.w"], p["head.b"]
    if tabled(cfg):
        every = add(matmul(codes, shape(move(w, (1, 0, 2)), (cfg.decoder_width, -1))), shape(b, (-1,)))
        return at_places(shape(every, (-1, 12)), t.owner * cfg.slots + t.slot)
    return add(slot_linear(take(codes, t.owner), w, t.slot), take(b, t.slot))


def _layout(sample: np.ndarray, n: int, extra: int = 0) -> Layout:
    """Places of the rows, after ``extra`` ones of every sample."""
    count = np.bincount(sample, minlength=n)
    order = np.argsort(sample, kind="stable")
    nth = np.empty(len(sample), np.int64)
    nth[order] = np.arange(len(sample)) - np.repeat(np.cumsum(count) - count, count)
    wide = max(1, int(count.max(initial=0)) + extra)
    return Layout(sample * wide + extra + nth, wide, np.arange(wide)[None] < (count + extra)[:, None])


def encode(t: Tokens, p: dict[str, Var], cfg: ModelConfig, only: str | None = None) -> tuple[Var | None, Var | None]:
    """(codes of the tokens, class code of each sample); ``only`` "tokens" or "class": nothing is worked out that the other alone needs."""
    x = add(embed(t, p, cfg), position(t.corner, p, "enc"))
    rest, many = _layout(t.sample, t.n, 1), len(t.sample)
    rows = stack_rows([x, take(p["cls"], np.zeros(t.n, np.int64))])
    hold = Layout(np.concatenate([rest.place, np.arange(t.n) * rest.wide]), rest.wide, rest.mask)
    tokens, classes = slice(0, many), slice(many, None)
    if only:
        at, ask = (classes, Layout(np.arange(t.n), 1, np.ones((t.n, 1), bool))) if only == "class" else (tokens, _layout(t.sample, t.n))
        out = transformer(rows, p, "enc", cfg.blocks, cfg.heads, hold, at, ask)
        return (None, out) if only == "class" else (out, None)
    out = transformer(rows, p, "enc", cfg.blocks, cfg.heads, hold)
    return at_places(out, tokens), at_places(out, classes)


def reconstruct(t: Tokens, hidden: np.ndarray, p: dict[str, Var], cfg: ModelConfig) -> tuple[Var, Tokens]:
    """Codes of the hidden tokens, decoded from the visible ones."""
    if tabled(cfg):
        t.table(cfg, p["slot.w"].value.dtype)
    vis, hid = t.pick(~hidden, not tabled(cfg)), t.pick(hidden)
    codes, _ = encode(vis, p, cfg, "tokens")
    seen = add(linear(codes, p, "adapt"), position(vis.corner, p, "dec"))
    blank = add(take(p["mask"], np.zeros(len(hid.sample), np.int64)), position(hid.corner, p, "dec"))
    hold = _layout(np.concatenate([vis.sample, hid.sample]), t.n)
    out = transformer(stack_rows([seen, blank]), p, "dec", cfg.decoder_blocks, cfg.decoder_heads, hold, slice(len(vis.sample), None), _layout(hid.sample, t.n))
    return out, hid


#: Distances that :func:`nearest` holds at a time.
NEAR = 1 << 18
#: Sizes of groups are rounded up to multiples of it, so that more groups are compared side by side.
SIDE = 8


def nearest(a: np.ndarray, b: np.ndarray, ga: np.ndarray, gb: np.ndarray, n: int) -> np.ndarray:
    """For each row of ``a`` the nearest row of ``b`` in the same group, the first of equals."""
    return nearest_both(a, b, ga, gb, n)[0]


def nearest_both(a: np.ndarray, b: np.ndarray, ga: np.ndarray, gb: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """:func:`nearest` from ``a`` to ``b`` and back, of the same products. Groups of about the same sizes are compared side by side."""
    to_b, to_a = np.zeros(len(a), np.int64), np.zeros(len(b), np.int64)
    oa, ob = np.argsort(ga, kind="stable"), np.argsort(gb, kind="stable")
    ca, cb = (np.searchsorted(g[o], np.arange(n + 1)) for g, o in ((ga, oa), (gb, ob)))
    na, nb = np.diff(ca), np.diff(cb)
    both = np.flatnonzero((na > 0) & (nb > 0))
    # sizes are rounded up by repeating the last row, which is never the first of equals
    ka, kb = (-(-c // SIDE) * SIDE for c in (na, nb))
    both = both[np.lexsort((kb[both], ka[both]))]
    if not len(both):
        return to_b, to_a
    cuts = np.flatnonzero((np.diff(ka[both]) != 0) | (np.diff(kb[both]) != 0)) + 1
    for same in np.split(both, cuts):
        k, m = int(ka[same[0]]), int(kb[same[0]])
        for lo in range(0, len(same), step := max(1, NEAR // (k * m))):
            part = same[lo : lo + step, None]
            i, j = oa[ca[part] + np.minimum(np.arange(k), na[part] - 1)], ob[cb[part] + np.minimum(np.arange(m), nb[part] - 1)]
            x, y = a[i], b[j]
            # the own square is the same for all candidates
            d = x @ (y * -2).transpose(0, 2, 1)
            d += (y * y).sum(-1)[:, None]
            to_b[i] = np.take_along_axis(j, d.argmin(2), 1)
            d += (x * x).sum(-1)[:, :, None]
            to_a[j] = np.take_along_axis(i, d.argmin(1), 1)
    return to_b, to_a


def chamfer(true: np.ndarray, pred: Var, gt: np.ndarray, gp: np.ndarray, n: int) -> Var:
    """Mean over groups of both means of squared distances to the nearest point of the other set."""
    true = true.astype(pred.value.dtype, copy=False)
    to_pred, to_true = nearest_both(true, pred.value, gt, gp, n)
    there, here = pred.value[to_pred] - true, pred.value - true[to_true]
    wt, wp = ((1 / (np.bincount(g, minlength=n)[g] * n)).astype(true.dtype)[:, None] for g in (gt, gp))

    def back(g):
        d, far = here * (2 * g * wp), there * (2 * g * wt)
        for c in range(d.shape[1]):
            d[:, c] += np.bincount(to_pred, far[:, c], len(d))
        return d

    return Var((there * there * wt).sum() + (here * here * wp).sum(), ((pred, back),))


def squares(a: Var, lo: int, hi: int, true: np.ndarray, w: np.ndarray) -> Var:
    """Weighted sum of the squares of what the columns ``lo`` to ``hi`` are off."""
    off = a.value[:, lo:hi] - true.astype(a.value.dtype, copy=False)

    def back(g):
        d = np.zeros_like(a.value)
        d[:, lo:hi] = off * (2 * g * w)
        return d

    return Var((off * off * w).sum(), ((a, back),))


def occupancy_bce(logit: Var, occupied: np.ndarray, eps: float = 1e-7) -> Var:
    """Mean over tokens and slots of the cross-entropy; probabilities are kept eps away from 0 and 1."""
    q = 1 / (1 + np.exp(-logit.value))
    c = np.clip(q, eps, 1 - eps)
    n = max(1, occupied.size)
    value = -(occupied * np.log(c) + (1 - occupied) * np.log(1 - c)).sum() / n
    return Var(value, ((logit, lambda g: g * np.where(c == q, q - occupied, 0.0) / n),))


def pretrain_loss(t: Tokens, hidden: np.ndarray, p: dict[str, Var], cfg: ModelConfig, terms=("mse", "cd", "occ")) -> tuple[Var, dict[str, float]]:
    codes, hid = reconstruct(t, hidden, p, cfg)
    n = len(hid.sample)
    if cfg.group:
        pred = shape(linear(codes, p, "points"), (n * cfg.group, 3))
        loss = chamfer(hid.feat, pred, hid.owner, np.repeat(np.arange(n), cfg.group), n)
        return loss, {"cd": float(loss.value)}
    made = unembed(codes, hid, p, cfg)
    kind, last = made.value.dtype, 12 if cfg.features == "graph" else 6
    w = (1 / (np.bincount(hid.owner, minlength=n)[hid.owner] * max(1, n))).astype(kind)
    occupied = np.zeros((n, cfg.slots), kind)
    occupied[hid.owner, hid.slot] = 1
    makes = {
        "mse": lambda: squares(made, 3, last, hid.feat[:, 3:last], w[:, None]),
        "cd": lambda: chamfer(hid.feat[:, :3], columns(made, 0, 3), hid.owner, hid.owner, n),
        "occ": lambda: occupancy_bce(linear(codes, p, "occ"), occupied),
    }
    parts = {k: makes[k]() for k in terms}
    loss = None
    for k in terms:
        loss = parts[k] if loss is None else add(loss, parts[k])
    return loss, {k: float(v.value) for k, v in parts.items()}


def cross_entropy(logit: Var, label: np.ndarray) -> Var:
    x = logit.value - logit.value.max(1, keepdims=True)
    p = np.exp(x) / np.exp(x).sum(1, keepdims=True)
    rows = np.arange(len(label))

    def back(g):
        d = p.copy()
        d[rows, label] -= 1
        return g * d / len(label)

    return Var(-np.log(np.maximum(p[rows, label], 1e-300)).mean(), ((logit, back),))


def gradients(loss_of, params: dict[str, np.ndarray]) -> tuple[float, dict[str, np.ndarray], dict]:
    p = {k: Var(v) for k, v in params.items()}
    loss, info = loss_of(p)
    loss.backward()
    return float(loss.value), {k: v.grad if v.grad is not None else np.zeros_like(v.value) for k, v in p.items()}, info


class AdamW:
    """Decoupled weight decay; biases, gains and single tokens are not decayed."""

    def __init__(self, lr: float = 5e-4, wd: float = 0.05, betas=(0.9, 0.95), eps: float = 1e-8):
        self.lr, self.wd, self.betas, self.eps, self.t, self.m, self.v = lr, wd, betas, eps, 0, {}, {}

    def step(self, params: dict[str, np.ndarray], grads: dict[str, np.ndarray], lr: float | None = None) -> dict[str, np.ndarray]:
        self.t += 1
        lr, (b1, b2), out = self.lr if lr is None else lr, self.betas, {}
        for k, w in params.items():
            g = grads[k]
            m = self.m[k] = b1 * self.m.get(k, 0.0) + (1 - b1) * g
            v = self.v[k] = b2 * self.v.get(k, 0.0) + (1 - b2) * g * g
            step = (m / (1 - b1**self.t)) / (np.sqrt(v / (1 - b2**self.t)) + self.eps)
            out[k] = w - lr * (step + (self.wd * w if w.ndim > 1 and min(w.shape) > 1 else 0.0))
        return out


def cosine(lr: float, t: int, total_steps: int, warmup: int = 0) -> float:
    if t < warmup:
        return lr * (t + 1) / warmup
    return lr * 0.5 * (1 + math.cos(math.pi * (t - warmup) / max(1, total_steps - warmup)))


# clouds to tokens ------------------------------------------------------------------------------------------------


def voxel_rows(pts: np.ndarray, cfg: ModelConfig) -> np.ndarray:
    """Numbers of the points that stand for their voxels, by voxel."""
    return voxel_rows_of(pts.T, cfg)


def voxel_rows_of(columns, cfg: ModelConfig) -> np.ndarray:
    """:func:`voxel_rows` of points given as six columns: of a voxel the point with the largest sum of attributes, the first of equals."""
    size = len(columns[0])
    if not size:
        return np.zeros(0, np.int64)
    flat = np.zeros(size, np.int64)
    for c in columns[:3]:
        key = np.floor(c / (1.0 / cfg.grid))
        np.clip(key, 0, cfg.grid - 1, out=key)
        flat *= cfg.grid
        flat += key.astype(np.int64)
    score = columns[0] + columns[1]
    for c in columns[2:]:
        score += c
    score = np.floor(score * 1e6 + 0.5)
    top, low = float(score.max()), float(score.min())
    bits, wide = size.bit_length(), int(top - low).bit_length() if np.isfinite(top - low) else 64
    if (cfg.grid**3).bit_length() + wide + bits < 64:
        # voxel, score and number fit one integer, and integers are sorted much faster than rows
        packed = flat << (wide + bits) | (top - score).astype(np.int64) << bits | np.arange(size)
        packed.sort()
        voxel, order = packed >> (wide + bits), packed & ((1 << bits) - 1)
    else:
        order = np.lexsort((-score, flat))
        voxel = flat[order]
    return order[np.concatenate(([True], voxel[1:] != voxel[:-1]))]


def voxel_tokens(clouds: list[np.ndarray], cfg: ModelConfig) -> Tokens:
    """Clouds (n, 6) -> the batch's tokens; the same rules as the DataFrame operators. All clouds are worked on at once."""
    pts, of = np.concatenate(clouds), np.repeat(np.arange(len(clouds)), [len(c) for c in clouds])
    key = np.clip(np.floor(pts[:, :3] / (1.0 / cfg.grid)), 0, cfg.grid - 1).astype(np.int64)
    flat = ((of * cfg.grid + key[:, 0]) * cfg.grid + key[:, 1]) * cfg.grid + key[:, 2]
    order = np.lexsort((-np.floor(pts.sum(1) * 1e6 + 0.5), flat))
    kept = order[np.concatenate(([True], np.diff(flat[order]) != 0))] if len(pts) else order
    attr, key, of = pts[kept], key[kept], of[kept]
    wide, at = -(-cfg.grid // cfg.patch), key // cfg.patch
    names, owner = np.unique(((of * wide + at[:, 0]) * wide + at[:, 1]) * wide + at[:, 2], return_inverse=True)
    order = np.argsort(owner, kind="stable")
    key, attr, owner = key[order], attr[order], owner[order]
    slot = (key % cfg.patch) @ np.array([1, cfg.patch, cfg.patch**2])
    n = np.bincount(owner, minlength=len(names))[:, None]
    centre = (sum_by(attr[:, :3], owner, len(names)) / np.maximum(n, 1))[owner]
    cell = np.stack([names // (wide * wide) % wide, names // wide % wide, names % wide], 1)
    return Tokens(names // wide**3, cell * cfg.patch / cfg.grid, owner, slot, np.hstack([attr, attr[:, :3] - centre, centre]), cell, len(clouds))


#: Clouds of equal sizes up to so many points are grouped side by side, so many distances at a time.
SMALL_CLOUD, DISTANCES = 128, 1 << 20


def centres_of(xyz: np.ndarray, centres: int) -> tuple[np.ndarray, np.ndarray]:
    """(clouds, size, 3) -> centres (clouds, ranks) as :func:`~pointloom.operators.baselines.fps_kernel` picks them, and the squared
    distances of all points (clouds, ranks, size)."""
    many, size = xyz.shape[:2]
    row, centres = np.arange(many), min(centres, size)
    taken, near = np.zeros((many, centres), np.int64), np.full((many, size), np.inf)
    far = np.empty((many, centres, size))
    for j in range(centres):
        d = xyz - xyz[row, taken[:, j]][:, None]
        d *= d
        far[:, j] = d[:, :, 0] + d[:, :, 1] + d[:, :, 2]
        if j + 1 < centres:
            np.minimum(near, far[:, j], out=near)
            taken[:, j + 1] = near.argmax(1)
    return taken, far


def group_tokens(clouds: list[np.ndarray], cfg: ModelConfig, centres: int = 16) -> Tokens:
    """Fixed-token tokens: sampled centres and their nearest neighbours, as offsets."""
    sizes = np.array([len(c) for c in clouds])
    order = np.argsort(sizes, kind="stable")
    found: list = [None] * len(clouds)
    for same in np.split(order, np.flatnonzero(np.diff(sizes[order])) + 1):
        size = int(sizes[same[0]])
        if not 0 < size <= SMALL_CLOUD:
            for s in same:
                at = fps_kernel(clouds[s][:, :3], centres)
                found[s] = at, nearest_kernel(clouds[s][:, :3], clouds[s][at, :3], cfg.group)[0]
            continue
        for lo in range(0, len(same), step := max(1, DISTANCES // (size * min(centres, size)))):
            part = same[lo : lo + step]
            taken, far = centres_of(np.stack([clouds[s][:, :3] for s in part]), centres)
            # nearest first, ties to the earlier, as nearest_kernel has them
            near = far.argsort(axis=2, kind="stable")[:, :, : cfg.group]
            for s, *own in zip(part, taken, near, strict=True):
                found[s] = own
    parts, base = [], 0
    for s, (pts, (at, near)) in enumerate(zip(clouds, found, strict=True)):
        xyz = pts[:, :3]
        off = (xyz[near] - xyz[at][:, None]).reshape(-1, 3)
        rank = np.stack([np.arange(len(at)), *[np.zeros(len(at), np.int64)] * 2], axis=1)
        parts.append((np.full(len(at), s), xyz[at], np.repeat(np.arange(len(at)), near.shape[1]) + base, np.zeros(len(off), np.int64), off, rank))
        base += len(at)
    return Tokens(*(np.concatenate(x) for x in zip(*parts, strict=True)), len(clouds))


class Clouds(list):
    """Clouds (n, 6) with their samples' numbers; their tokens are made once for all models of the same lattice."""

    def __init__(self, clouds, ids: np.ndarray):
        super().__init__(clouds)
        self.ids, self.made = ids, {}


def tokens_of(clouds: list[np.ndarray], cfg: ModelConfig) -> Tokens:
    made, key = getattr(clouds, "made", {}), (cfg.group,) if cfg.group else (0, cfg.grid, cfg.patch)
    if key not in made:
        made[key] = group_tokens(clouds, cfg) if cfg.group else voxel_tokens(clouds, cfg)
        made[key].ids = getattr(clouds, "ids", None)
    return made[key]


def hide(t: Tokens, percent: int, seed: int) -> np.ndarray:
    """count * percent div 100 tokens of every sample, first by an order hashed from the seed, the sample and the cell, ties by
    cell: the mask of :func:`pointloom.operators.masking.random_mask`, whatever batch the sample comes in."""
    if ("order", seed) not in t.made:
        ids = np.arange(t.n) if t.ids is None else np.asarray(t.ids, np.int64)
        rank = draw_of(seed, ids[t.sample], *t.cell.T)
        order = np.lexsort((*t.cell.T[::-1], rank, t.sample))
        count = np.bincount(t.sample, minlength=t.n)
        nth = np.empty(len(order), np.int64)
        nth[order] = np.arange(len(order)) - np.repeat(np.cumsum(count) - count, count)
        t.made["order", seed] = nth, count
    nth, count = t.made["order", seed]
    return nth < (count * percent // 100)[t.sample]
