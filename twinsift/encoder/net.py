"""The chunk encoder: code-point bits, a few blocks, pooling, a dense projection to unit vectors."""

import math
from dataclasses import dataclass, replace

import numpy as np

from twinsift.encoder.tape import Node, join, wrap
from twinsift.functions.shipping import by_value

by_value(__name__)

BITS = 24
BLOCKS = ("gau", "mlp", "conv", "bert", "t5")
POOLS = ("gem", "avg", "max")


@dataclass(frozen=True)
class Config:
    chunk: int = 512
    hidden: int = 256
    blocks: int = 2
    dim: int = 256
    block: str = "gau"
    pool: str = "gem"
    qk: int = 128
    heads: int = 4
    bias_table: bool = True
    p: float = 3.0


PRESETS = {"paper": Config(), "small": Config(hidden=64, dim=64, qk=32), "tiny": Config(chunk=128, hidden=64, dim=128, qk=32)}

# The grids of the ablations, as published.
GRID = {"block": BLOCKS, "chunk": (128, 256, 512, 1024, 2048), "dim": (64, 128, 256, 512, 768), "pool": ("avg", "max", "gem"), "blocks x hidden": tuple((b, h) for b in (2, 3, 4) for h in (64, 128, 256, 512))}


def grid(base: Config, factor: str) -> list[Config]:
    """The configurations of one ablation, everything else as in base."""
    if factor == "blocks x hidden":
        return [replace(base, blocks=b, hidden=h) for b, h in GRID[factor]]
    return [replace(base, **{factor: v}) for v in GRID[factor]]


def code_points(texts: list[str], length: int) -> tuple[np.ndarray, np.ndarray]:
    """(n, length) of code points, and which places hold a character. Texts must not be longer."""
    points = np.zeros((len(texts), length), np.uint32)
    mask = np.zeros((len(texts), length), np.float32)
    for i, t in enumerate(texts):
        own = np.frombuffer(t.encode("utf-32-le", "surrogatepass"), np.uint32)
        points[i, : len(own)], mask[i, : len(own)] = own, 1
    return points, mask


def bits(texts: list[str], length: int) -> tuple[np.ndarray, np.ndarray]:
    """(n, length, 24) of 0 and 1, lowest bit first, and which places hold a character. Texts must not be longer."""
    points, mask = code_points(texts, length)
    return (points[..., None] >> np.arange(BITS, dtype=np.uint32) & 1).astype(np.float32), mask


def unbits(x: np.ndarray, mask: np.ndarray) -> list[str]:
    points = (x.astype(np.uint32) << np.arange(BITS, dtype=np.uint32)).sum(-1).astype(np.uint32)
    return [p[m > 0].astype("<u4").tobytes().decode("utf-32-le", "surrogatepass") for p, m in zip(points, mask, strict=True)]


def shapes(c: Config) -> dict[str, tuple]:
    """Name and shape of every weight."""
    h, out = c.hidden, {"in.w": (BITS, c.hidden), "in.b": (c.hidden,), "pos.s": (1,)}
    for i in range(c.blocks):
        k = f"{i}."
        if c.block == "gau":
            out |= {k + "norm": (1,), k + "w": (h, 2 * h + c.qk), k + "b": (2 * h + c.qk,), k + "g": (2, c.qk), k + "o": (2, c.qk), k + "out.w": (h, h), k + "out.b": (h,)}
            if c.bias_table:
                out[k + "rel"] = (2 * c.chunk - 1,)
        elif c.block == "mlp":
            out |= {k + "norm": (1,), k + "w1": (h, 4 * h), k + "b1": (4 * h,), k + "w2": (4 * h, h), k + "b2": (h,)}
        elif c.block == "conv":
            out |= {k + "norm": (1,), k + "taps": (7, h), k + "w1": (h, 4 * h), k + "b1": (4 * h,), k + "w2": (4 * h, h), k + "b2": (h,)}
        else:
            out |= {k + "qkv": (h, 3 * h), k + "qkv.b": (3 * h,), k + "out.w": (h, h), k + "out.b": (h,), k + "w1": (h, 4 * h), k + "b1": (4 * h,), k + "w2": (4 * h, h), k + "b2": (h,), k + "n1": (2, h), k + "n2": (2, h)}
            if c.block == "t5":
                out[k + "rel"] = (2 * c.chunk - 1,)
    return out | {"norm": (1,), "proj.w": (h, c.dim), "proj.b": (c.dim,)}


def n_params(c: Config) -> int:
    return sum(math.prod(s) for s in shapes(c).values())


def init(c: Config, seed: int = 0) -> dict[str, np.ndarray]:
    rng, out = np.random.default_rng(seed), {}
    for name, shape in shapes(c).items():
        last = name.rsplit(".", 1)[-1]
        if name == "pos.s":
            value = np.full(shape, c.hidden**-0.5)
        elif last in ("norm",):
            value = np.ones(shape)
        elif last == "g":
            value = 1 + rng.normal(0, 0.02, shape)
        elif last in ("n1", "n2"):
            value = np.stack([np.ones(shape[1]), np.zeros(shape[1])])
        elif last in ("b", "b1", "b2", "o", "rel"):
            value = np.zeros(shape)
        else:
            value = rng.normal(0, (2.0 / (shape[0] + shape[-1])) ** 0.5, shape)
        out[name] = value.astype(np.float32)
    return out


def waves(length: int, width: int) -> np.ndarray:
    at = np.arange(length)[:, None] / 10000 ** (np.arange(0, width, 2)[None] / width)
    return np.stack([np.sin(at), np.cos(at)], -1).reshape(length, -1)[:, :width].astype(np.float32)


def rotate(x: Node, length: int, width: int) -> Node:
    """Rotary positions over the two halves of the width."""
    half = width // 2
    angle = np.arange(length)[:, None] / 10000 ** (np.arange(half)[None] / half)
    cos, sin = np.cos(angle).astype(np.float32), np.sin(angle).astype(np.float32)
    a, b = x.part(0, half), x.part(half, width)
    return join(a * cos - b * sin, b * cos + a * sin)


def scale_norm(x: Node, g: Node) -> Node:
    size = ((x * x).mean(-1).clip_low(1e-10)) ** 0.5
    return x / size * g


def layer_norm(x: Node, w: Node) -> Node:
    centred = x - x.mean(-1)
    return centred / (((centred * centred).mean(-1) + 1e-5) ** 0.5) * w[0] + w[1]


def _relative(table: Node, length: int, chunk: int) -> Node:
    return table[np.arange(length)[None] - np.arange(length)[:, None] + chunk - 1]


def gated_attention(x: Node, w: dict, k: str, c: Config, mask: np.ndarray) -> Node:
    h, n = c.hidden, x.shape[1]
    made = (scale_norm(x, w[k + "norm"]) @ w[k + "w"] + w[k + "b"]).swish()
    u, v, z = made.part(0, h), made.part(h, 2 * h), made.part(2 * h, 2 * h + c.qk)
    q, key = (rotate(z * w[k + "g"][i] + w[k + "o"][i], n, c.qk) for i in (0, 1))
    scores = q @ key.swap() * (1.0 / n)
    if c.bias_table:
        scores = scores + _relative(w[k + "rel"], n, c.chunk)
    a = scores.relu()
    return x + (u * ((a * a * mask[:, None, :]) @ v)) @ w[k + "out.w"] + w[k + "out.b"]


def mlp(x: Node, w: dict, k: str, c: Config, mask: np.ndarray) -> Node:
    return x + (scale_norm(x, w[k + "norm"]) @ w[k + "w1"] + w[k + "b1"]).relu() @ w[k + "w2"] + w[k + "b2"]


def conv(x: Node, w: dict, k: str, c: Config, mask: np.ndarray) -> Node:
    held, total = x * mask[..., None], None
    for t in range(7):
        part = held.shift(t - 3) * w[k + "taps"][t]
        total = part if total is None else total + part
    return x + (scale_norm(total, w[k + "norm"]) @ w[k + "w1"] + w[k + "b1"]).swish() @ w[k + "w2"] + w[k + "b2"]


def attention(x: Node, w: dict, k: str, c: Config, mask: np.ndarray) -> Node:
    """Multi-head attention; BERT-like norms after each part, T5-like before, with a table of relative biases."""
    h, n, heads, t5 = c.hidden, x.shape[1], c.heads, c.block == "t5"
    qkv = (layer_norm(x, w[k + "n1"]) if t5 else x) @ w[k + "qkv"] + w[k + "qkv.b"]
    q, key, v = (qkv.part(i * h, (i + 1) * h).reshape(-1, n, heads, h // heads).swap(1, 2) for i in range(3))
    scores = q @ key.swap() * (h // heads) ** -0.5 + ((mask - 1) * 1e4)[:, None, None, :]
    if t5:
        scores = scores + _relative(w[k + "rel"], n, c.chunk)
    mixed = (scores.softmax() @ v).swap(1, 2).reshape(-1, n, h) @ w[k + "out.w"] + w[k + "out.b"]
    x = x + mixed if t5 else layer_norm(x + mixed, w[k + "n1"])
    wide = ((layer_norm(x, w[k + "n2"]) if t5 else x) @ w[k + "w1"] + w[k + "b1"]).relu() @ w[k + "w2"] + w[k + "b2"]
    return x + wide if t5 else layer_norm(x + wide, w[k + "n2"])


APPLY = {"gau": gated_attention, "mlp": mlp, "conv": conv, "bert": attention, "t5": attention}


def pool(x: Node, mask: np.ndarray, kind: str = "gem", p: float = 3.0, eps: float = 1e-6) -> Node:
    """One vector for each text from the places that hold characters."""
    m, count = mask[..., None], np.maximum(mask.sum(1, keepdims=True), 1)[..., None]
    if kind == "max":
        out = (x * m + (m - 1) * 1e4).max(1)
    elif kind == "avg":
        out = (x * m).sum(1) * (1.0 / count)
    else:
        out = (((x.clip_low(eps) ** p) * m).sum(1) * (1.0 / count)).clip_low(eps**p) ** (1.0 / p)
    return out.reshape(-1, x.shape[-1])


def forward(w: dict[str, Node], c: Config, x: np.ndarray, mask: np.ndarray) -> Node:
    """Unit vectors of chunks given as bits."""
    n = x.shape[1]
    h = wrap(x) @ w["in.w"] + w["in.b"] + waves(n, c.hidden) * w["pos.s"]
    for i in range(c.blocks):
        h = APPLY[c.block](h, w, f"{i}.", c, mask)
    y = pool(scale_norm(h, w["norm"]), mask, c.pool, c.p) @ w["proj.w"] + w["proj.b"]
    return y / (((y * y).sum(-1) + 1e-12) ** 0.5)


KNOWN = 4096  # code points whose first layer is computed beforehand
PLACED = 256  # code points whose whole way to the first attention is computed beforehand, for each place of a full chunk
LEAN = 1024  # characters at a time, so that arrays stay in a core's cache


class _Gated:
    """The numbers of `forward` for gated attention with power-mean pooling, without what gradients need: the first layer is looked up,
    norms, rotations and masks go into smaller factors, and arrays are changed in place."""

    def __init__(self, w: dict[str, np.ndarray], c: Config):
        self.w, self.c, self.tables, self.rooms = w, c, {}, {}
        self.placed, self.held = None, {}
        self.first = self._first(np.arange(KNOWN, dtype=np.uint32))

    def _first(self, points: np.ndarray) -> np.ndarray:
        return (points[:, None] >> np.arange(BITS, dtype=np.uint32) & 1).astype(np.float32) @ self.w["in.w"] + self.w["in.b"]

    def _table(self, length: int) -> tuple:
        """What depends on the length alone: positions, and of each block the factors of queries and keys and the relative biases."""
        if length not in self.tables:
            w, c = self.w, self.c
            half = c.qk // 2
            angle = np.arange(length)[:, None] / 10000 ** (np.arange(half)[None] / half)
            cos, sin = np.cos(angle).astype(np.float32), np.sin(angle).astype(np.float32)
            apart = np.arange(length)[None] - np.arange(length)[:, None] + c.chunk - 1
            blocks = []
            for i in range(c.blocks):
                g, o, sides = w[f"{i}.g"], w[f"{i}.o"], []
                for k, scale in ((0, np.float32(1.0 / length)), (1, np.float32(1))):
                    (ga, gb), (oa, ob) = np.split(g[k] * scale, 2), np.split(o[k] * scale, 2)
                    sides.append((np.concatenate([ga * cos, gb * cos], -1), np.concatenate([-gb * sin, ga * sin], -1), np.concatenate([oa * cos - ob * sin, ob * cos + oa * sin], -1)))
                blocks.append((sides, w[f"{i}.rel"][apart] if c.bias_table else None))
            self.tables[length] = waves(length, c.hidden) * w["pos.s"], blocks
        return self.tables[length]

    @staticmethod
    def _scale(x: np.ndarray, g: np.ndarray) -> np.ndarray:
        return g / np.sqrt(np.maximum(np.einsum("ij,ij->i", x, x)[:, None] / np.float32(x.shape[1]), np.float32(1e-10)))

    def _room(self, n: int, length: int) -> tuple:
        """Arrays that are used again: fresh ones cost more than what is computed in them."""
        if (n, length) not in self.rooms:
            c, rows = self.c, n * length
            wide = 2 * c.hidden + c.qk
            sizes = ((rows, c.hidden), (rows, wide), (rows, wide), (n, length, c.qk), (n, length, c.qk), (n, length, c.qk), (n, length, c.qk), (n, c.qk, length), (n, length, length), (n, length, c.hidden), (rows, c.hidden))
            self.rooms[n, length] = tuple(np.empty(s, np.float32) for s in sizes)
        return self.rooms[n, length]

    def _gates(self, i: int, sides: list, room: tuple) -> None:
        """Gates, values, queries and keys of block i from what the room holds."""
        w, c, k, half = self.w, self.c, f"{i}.", self.c.qk // 2
        x, made, e, turned, q, key, part = room[:7]
        np.matmul(x, w[k + "w"], out=made)
        made *= self._scale(x, w[k + "norm"])
        made += w[k + "b"]
        np.negative(made, out=e)
        with np.errstate(over="ignore"):
            np.exp(e, out=e)
        e += 1
        made /= e
        z = made[:, 2 * c.hidden :].reshape(turned.shape)
        turned[..., :half], turned[..., half:] = z[..., half:], z[..., :half]
        for side, (straight, crossed, fixed) in zip((q, key), sides, strict=True):
            np.multiply(z, straight, out=side)
            np.multiply(turned, crossed, out=part)
            side += part
            side += fixed

    def _places(self) -> tuple:
        """What the first block makes of a code point at a place of a full chunk, before places meet: it depends on nothing else."""
        if self.placed is None:
            c = self.c
            place, blocks = self._table(c.chunk)
            out = tuple(np.empty((PLACED * c.chunk, width), np.float32) for width in (c.hidden, 2 * c.hidden, c.qk, c.qk))
            step = max(1, LEAN // c.chunk)
            for a in range(0, PLACED, step):
                n = min(step, PLACED - a)
                room = self._room(n, c.chunk)
                np.add(self.first[a : a + n, None], place, out=room[0].reshape(n, c.chunk, -1))
                own = slice(a * c.chunk, (a + n) * c.chunk)
                out[0][own] = room[0]
                self._gates(0, blocks[0][0], room)
                out[1][own] = room[1][:, : 2 * c.hidden]
                for k in (2, 3):
                    out[k][own] = room[k + 2].reshape(n * c.chunk, -1)
            self.placed = out
        return self.placed

    def run(self, points: np.ndarray, mask: np.ndarray, placed: bool = False) -> np.ndarray:
        """placed: whether the texts are full chunks of code points below PLACED."""
        w, c = self.w, self.c
        n, length = points.shape
        place, blocks = self._table(length)
        tables = self._places() if placed else ()
        room = self._room(n, length)
        x, made, _, _, q, key, _, across, scores, mixed, more = room
        if placed:
            if n not in self.held:
                self.held[n] = np.empty((n * length, 2 * c.hidden), np.float32)
            at = (points.astype(np.int64) * length + np.arange(length)).ravel()
            for table, out in zip(tables, (x, self.held[n], q.reshape(n * length, -1), key.reshape(n * length, -1)), strict=True):
                np.take(table, at, axis=0, out=out, mode="clip")
        else:
            if points.max(initial=0) < KNOWN:
                np.take(self.first, points.ravel(), axis=0, out=x, mode="clip")
            else:
                own, at = np.unique(points, return_inverse=True)
                np.take(self._first(own), at.ravel(), axis=0, out=x, mode="clip")
            x.reshape(n, length, -1)[...] += place
        whole = bool((mask == 1).all())
        for i, (sides, rel) in enumerate(blocks):
            k = f"{i}."
            if i or not placed:
                self._gates(i, sides, room)
            gates = made if i or not placed else self.held[n]
            u, v = gates[:, : c.hidden], gates[:, c.hidden : 2 * c.hidden].reshape(n, length, -1)
            across[...] = key.swapaxes(1, 2)
            np.matmul(q, across, out=scores)
            if rel is not None:
                scores += rel
            np.maximum(scores, 0, out=scores)
            scores *= scores
            if not whole:
                v *= mask[..., None]
            np.matmul(scores, v, out=mixed)
            flat = mixed.reshape(n * length, -1)
            flat *= u
            np.matmul(flat, w[k + "out.w"], out=more)
            x += more
            x += w[k + "out.b"]
        x *= self._scale(x, w["norm"])
        low = np.float32(1e-6)
        np.maximum(x, low, out=x)
        if c.p == 3:
            np.multiply(x, x, out=more)
            more *= x
        else:
            np.power(x, c.p, out=more)
        cube = more.reshape(n, length, -1)
        if not whole:
            cube *= mask[..., None]
        pooled = cube.sum(1) / np.maximum(mask.sum(1), 1)[:, None]
        y = np.maximum(pooled, low**c.p) ** np.float32(1.0 / c.p) @ w["proj.w"] + w["proj.b"]
        return y / np.sqrt((y * y).sum(-1, keepdims=True) + np.float32(1e-12))


def lean(weights: dict[str, np.ndarray], c: Config) -> _Gated | None:
    """What `encode` may use again for many calls, where there is such a form."""
    return _Gated(weights, c) if c.block == "gau" and c.pool == "gem" else None


def encode(weights: dict[str, np.ndarray], c: Config, texts: list[str], batch: int = 64, ready: _Gated | None = None) -> np.ndarray:
    """Vectors of chunk texts. Attention is divided by the padded length, so only texts of one padded length share a batch: a text's vector is the same in any company.
    ready: as `lean` gives it for these weights; a task that has many texts to encode makes it once."""
    fast = ready or lean(weights, c)
    w = None if fast else {k: Node(v, track=False) for k, v in weights.items()}
    out = np.zeros((len(texts), c.dim), np.float32)
    padded = np.array([min(c.chunk, -(-max(1, len(t)) // 16) * 16) for t in texts], np.int64)
    if ready:
        full = np.array([len(t) == c.chunk and ord(max(t)) < PLACED for t in texts], bool)
        padded[full] = 0  # by the text alone, so equal texts have equal vectors
    for length in np.unique(padded).tolist():
        group, width = np.flatnonzero(padded == length), length or c.chunk
        step = max(1, LEAN // width) if fast else batch
        for a in range(0, len(group), step):
            own = group[a : a + step]
            some = [texts[i] for i in own]
            points, mask = code_points(some, width)
            mask[:, 0] = np.maximum(mask[:, 0], 1e-6)
            out[own] = fast.run(points, mask, not length) if fast else forward(w, c, bits(some, width)[0], mask).value
    return out
