"""Reverse-mode gradients over numpy arrays: as much as the encoder needs."""

import numpy as np

from twinsift.functions.shipping import by_value

by_value(__name__)


def _fit(grad: np.ndarray, shape: tuple) -> np.ndarray:
    """Sum a gradient over the axes that broadcasting added."""
    while grad.ndim > len(shape):
        grad = grad.sum(0)
    for i, n in enumerate(shape):
        if n == 1 and grad.shape[i] != 1:
            grad = grad.sum(i, keepdims=True)
    return grad


class Node:
    """An array, and how its gradient flows to what it was made from."""

    __array_priority__ = 100

    def __init__(self, value, parents=(), track: bool | None = None):
        self.value = np.asarray(value, np.float32) if not isinstance(value, np.ndarray) else value
        self.track = any(p.track for p, _ in parents) if track is None else track
        self.parents = [(p, f) for p, f in parents if p.track] if self.track else []
        self.grad = None

    shape = property(lambda self: self.value.shape)

    def backward(self, seed=None) -> None:
        order, seen, stack = [], set(), [(self, False)]
        while stack:
            node, done = stack.pop()
            if done:
                order.append(node)
            elif id(node) not in seen:
                seen.add(id(node))
                stack.append((node, True))
                stack += [(p, False) for p, _ in node.parents]
        self.grad = np.ones_like(self.value) if seed is None else seed
        for node in reversed(order):
            for parent, flow in node.parents:
                g = _fit(flow(node.grad), parent.value.shape)
                parent.grad = g if parent.grad is None else parent.grad + g

    def __add__(self, o):
        o = wrap(o)
        return Node(self.value + o.value, [(self, lambda g: g), (o, lambda g: g)])

    __radd__ = __add__

    def __mul__(self, o):
        o = wrap(o)
        return Node(self.value * o.value, [(self, lambda g: g * o.value), (o, lambda g: g * self.value)])

    __rmul__ = __mul__

    def __neg__(self):
        return self * -1.0

    def __sub__(self, o):
        return self + -wrap(o)

    def __rsub__(self, o):
        return wrap(o) + -self

    def __truediv__(self, o):
        return self * wrap(o) ** -1.0

    def __pow__(self, p: float):
        return Node(self.value**p, [(self, lambda g: g * p * self.value ** (p - 1))])

    def __matmul__(self, o):
        o = wrap(o)
        return Node(self.value @ o.value, [(self, lambda g: g @ np.swapaxes(o.value, -1, -2)), (o, lambda g: np.swapaxes(self.value, -1, -2) @ g if self.value.ndim == o.value.ndim else self.value.reshape(-1, self.value.shape[-1]).T @ g.reshape(-1, g.shape[-1]))])

    def __getitem__(self, key):
        def flow(g):
            out = np.zeros_like(self.value)
            np.add.at(out, key, g)
            return out

        return Node(self.value[key], [(self, flow)])

    def part(self, a: int, b: int):
        """Columns a to b of the last axis."""
        def flow(g):
            out = np.zeros_like(self.value)
            out[..., a:b] = g
            return out

        return Node(self.value[..., a:b], [(self, flow)])

    def swap(self, a: int = -1, b: int = -2):
        return Node(np.swapaxes(self.value, a, b), [(self, lambda g: np.swapaxes(g, a, b))])

    def reshape(self, *shape):
        was = self.value.shape
        return Node(self.value.reshape(shape), [(self, lambda g: g.reshape(was))])

    def sum(self, axis=None, keepdims=True):
        def flow(g):
            if not keepdims and axis is not None:
                g = np.expand_dims(g, axis)
            return np.broadcast_to(g, self.value.shape)

        return Node(self.value.sum(axis=axis, keepdims=keepdims), [(self, flow)])

    def mean(self, axis=-1):
        return self.sum(axis) * (1.0 / self.value.shape[axis])

    def max(self, axis: int):
        top = self.value.max(axis, keepdims=True)
        hit = (self.value == top) / np.maximum((self.value == top).sum(axis, keepdims=True), 1)
        return Node(top, [(self, lambda g: g * hit)])

    def exp(self):
        v = np.exp(self.value)
        return Node(v, [(self, lambda g: g * v)])

    def log(self):
        return Node(np.log(self.value), [(self, lambda g: g / self.value)])

    def clip_low(self, low: float):
        keep = self.value > low
        return Node(np.where(keep, self.value, np.float32(low)), [(self, lambda g: g * keep)])

    def relu(self):
        return self.clip_low(0.0)

    def swish(self):
        s = 1 / (1 + np.exp(-self.value))
        return Node(self.value * s, [(self, lambda g: g * (s + self.value * s * (1 - s)))])

    def softmax(self):
        e = np.exp(self.value - self.value.max(-1, keepdims=True))
        p = e / e.sum(-1, keepdims=True)
        return Node(p, [(self, lambda g: p * (g - (g * p).sum(-1, keepdims=True)))])

    def shift(self, k: int):
        """Rows moved by k along the second last axis, zeros moving in."""
        def move(v, k):
            out = np.zeros_like(v)
            if k > 0:
                out[..., k:, :] = v[..., :-k, :]
            elif k < 0:
                out[..., :k, :] = v[..., -k:, :]
            else:
                out[...] = v
            return out

        return Node(move(self.value, k), [(self, lambda g: move(g, -k))])


def wrap(x) -> Node:
    return x if isinstance(x, Node) else Node(np.asarray(x, np.float32), track=False)


def join(a: Node, b: Node) -> Node:
    n = a.value.shape[-1]
    return Node(np.concatenate([a.value, b.value], -1), [(a, lambda g: g[..., :n]), (b, lambda g: g[..., n:])])
