"""A small reverse-mode tape over NumPy arrays: what the pose model needs, and no more."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


def _fold(g: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Undo broadcasting: sum a gradient to the shape of what was broadcast."""
    while g.ndim > len(shape):
        g = g.sum(0)
    for axis, n in enumerate(shape):
        if n == 1 and g.shape[axis] != 1:
            g = g.sum(axis, keepdims=True)
    return g


class Node:
    def __init__(self, value, parents: tuple[tuple[Node, Callable], ...] = ()) -> None:
        self.value = np.asarray(value, float)
        self.parents = parents
        self.grad: np.ndarray | None = None

    def __add__(self, o: Node | float) -> Node:
        o = o if isinstance(o, Node) else Node(o)
        return Node(self.value + o.value, ((self, lambda g: _fold(g, self.value.shape)), (o, lambda g: _fold(g, o.value.shape))))

    def __mul__(self, o: Node | float) -> Node:
        o = o if isinstance(o, Node) else Node(o)
        return Node(self.value * o.value, ((self, lambda g: _fold(g * o.value, self.value.shape)), (o, lambda g: _fold(g * self.value, o.value.shape))))

    def __sub__(self, o: Node | float) -> Node:
        return self + (o if isinstance(o, Node) else Node(o)) * -1.0

    def __matmul__(self, o: Node) -> Node:
        t = lambda x: np.swapaxes(x, -1, -2)
        return Node(self.value @ o.value, ((self, lambda g: _fold(g @ t(o.value), self.value.shape)), (o, lambda g: _fold(t(self.value) @ g, o.value.shape))))

    def reshape(self, *shape: int) -> Node:
        return Node(self.value.reshape(shape), ((self, lambda g: g.reshape(self.value.shape)),))

    def transpose(self, *axes: int) -> Node:
        back = np.argsort(axes)
        return Node(self.value.transpose(axes), ((self, lambda g: g.transpose(back)),))

    def relu(self) -> Node:
        on = self.value > 0
        return Node(self.value * on, ((self, lambda g: g * on),))

    def softmax(self) -> Node:
        e = np.exp(self.value - self.value.max(-1, keepdims=True))
        s = e / e.sum(-1, keepdims=True)
        return Node(s, ((self, lambda g: s * (g - (g * s).sum(-1, keepdims=True))),))

    def normalised(self, eps: float = 1e-5) -> Node:
        """Zero mean and unit variance over the last axis."""
        c = self.value - self.value.mean(-1, keepdims=True)
        r = 1 / np.sqrt((c * c).mean(-1, keepdims=True) + eps)
        y = c * r
        return Node(y, ((self, lambda g: r * (g - g.mean(-1, keepdims=True) - y * (g * y).mean(-1, keepdims=True))),))

    def mean(self) -> Node:
        n = self.value.size
        return Node(self.value.mean(), ((self, lambda g: np.full(self.value.shape, float(g) / n)),))

    def abs(self) -> Node:
        sign = np.sign(self.value)
        return Node(np.abs(self.value), ((self, lambda g: g * sign),))

    def lengths(self, eps: float = 1e-12) -> Node:
        """Euclidean length over the last axis."""
        n = np.sqrt((self.value**2).sum(-1) + eps)
        return Node(n, ((self, lambda g: (g / n)[..., None] * self.value),))

    def backward(self) -> None:
        order: list[Node] = []
        seen: set[int] = set()
        stack = [(self, False)]
        while stack:
            node, done = stack.pop()
            if done:
                order.append(node)
            elif id(node) not in seen:
                seen.add(id(node))
                stack.append((node, True))
                stack += [(p, False) for p, _ in node.parents]
        self.grad = np.ones_like(self.value)
        for node in reversed(order):
            for parent, rule in node.parents:
                g = rule(node.grad)
                parent.grad = g if parent.grad is None else parent.grad + g


def concat(a: Node, b: Node) -> Node:
    """Along the last axis."""
    n = a.value.shape[-1]
    return Node(np.concatenate([a.value, b.value], -1), ((a, lambda g: g[..., :n]), (b, lambda g: g[..., n:])))


def straight_through(p: Node, q: np.ndarray) -> Node:
    """q forward, the identity backward."""
    return Node(q, ((p, lambda g: g),))
