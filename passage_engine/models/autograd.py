"""A small reverse-mode differentiator over numpy arrays, enough for the encoders and taggers."""

from __future__ import annotations

import numpy as np


class Var:
    """An array with the way back to what it was made of."""

    __slots__ = ("value", "grad", "back", "needs")

    def __init__(self, value, back=(), needs: bool = False):
        self.value = value
        self.back = back  # (parent, function from this gradient to the parent's)
        self.needs = needs or any(p.needs for p, _ in back)
        self.grad = None

    def __add__(self, o):
        o = lift(o)
        return Var(self.value + o.value, [(self, lambda g: reduce_to(g, self.value.shape)), (o, lambda g: reduce_to(g, o.value.shape))])

    def __mul__(self, o):
        o = lift(o)
        return Var(self.value * o.value, [(self, lambda g: reduce_to(g * o.value, self.value.shape)), (o, lambda g: reduce_to(g * self.value, o.value.shape))])

    def __sub__(self, o):
        return self + lift(o) * -1.0

    def __matmul__(self, o):
        o = lift(o)
        return Var(self.value @ o.value, [(self, lambda g: reduce_to(g @ np.swapaxes(o.value, -1, -2), self.value.shape)), (o, lambda g: reduce_to(np.swapaxes(self.value, -1, -2) @ g, o.value.shape))])

    def reshape(self, *shape):
        return Var(self.value.reshape(shape), [(self, lambda g: g.reshape(self.value.shape))])

    def transpose(self, *axes):
        return Var(self.value.transpose(axes), [(self, lambda g: g.transpose(np.argsort(axes)))])

    def __getitem__(self, at):
        def back(g):
            out = np.zeros_like(self.value)
            np.add.at(out, at, g)
            return out

        return Var(self.value[at], [(self, back)])

    def backward(self):
        order, seen = [], set()
        stack = [(self, False)]
        while stack:
            v, done = stack.pop()
            if done:
                order.append(v)
            elif id(v) not in seen and v.needs:
                seen.add(id(v))
                stack.append((v, True))
                stack += [(p, False) for p, _ in v.back]
        self.grad = np.ones_like(self.value)
        for v in reversed(order):
            for p, f in v.back:
                if p.needs:
                    g = f(v.grad)
                    p.grad = g if p.grad is None else p.grad + g


def lift(x) -> Var:
    return x if isinstance(x, Var) else Var(np.asarray(x, float))


def reduce_to(g: np.ndarray, shape: tuple) -> np.ndarray:
    """Sum over the axes that broadcasting added or stretched."""
    while g.ndim > len(shape):
        g = g.sum(axis=0)
    for i, n in enumerate(shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(axis=i, keepdims=True)
    return g


def gelu(x: Var) -> Var:
    c, square = np.sqrt(2 / np.pi), x.value * x.value
    t = np.tanh(c * (x.value + 0.044715 * square * x.value))
    slope = 0.5 * (1 + t) + 0.5 * x.value * (1 - t * t) * c * (1 + 3 * 0.044715 * square)
    return Var(0.5 * x.value * (1 + t), [(x, lambda g: g * slope)])


def tanh(x: Var) -> Var:
    t = np.tanh(x.value)
    return Var(t, [(x, lambda g: g * (1 - t * t))])


def sigmoid(x: Var) -> Var:
    s = 1 / (1 + np.exp(-np.clip(x.value, -60, 60)))
    return Var(s, [(x, lambda g: g * s * (1 - s))])


def softmax(x: Var) -> Var:
    e = np.exp(x.value - x.value.max(axis=-1, keepdims=True))
    s = e / e.sum(axis=-1, keepdims=True)
    return Var(s, [(x, lambda g: s * (g - (g * s).sum(axis=-1, keepdims=True)))])


def norm(x: Var, gain: Var, bias: Var, eps: float = 1e-6) -> Var:
    mean = x.value.mean(axis=-1, keepdims=True)
    scale = 1 / np.sqrt(((x.value - mean) ** 2).mean(axis=-1, keepdims=True) + eps)
    y = (x.value - mean) * scale
    unit = Var(y, [(x, lambda g: scale * (g - g.mean(axis=-1, keepdims=True) - y * (g * y).mean(axis=-1, keepdims=True)))])
    return unit * gain + bias


def concat(xs: list[Var], axis: int = -1) -> Var:
    cuts = np.cumsum([x.value.shape[axis] for x in xs])[:-1]
    return Var(np.concatenate([x.value for x in xs], axis=axis), [(x, lambda g, i=i: np.split(g, cuts, axis=axis)[i]) for i, x in enumerate(xs)])


def stack(xs: list[Var], axis: int = 0) -> Var:
    return Var(np.stack([x.value for x in xs], axis=axis), [(x, lambda g, i=i: np.take(g, i, axis=axis)) for i, x in enumerate(xs)])


def cross_entropy(logits: Var, y: np.ndarray, weight: np.ndarray) -> Var:
    """Summed softmax cross entropy of rows with weight; y holds classes."""
    z = logits.value - logits.value.max(axis=-1, keepdims=True)
    logp = z - np.log(np.exp(z).sum(axis=-1, keepdims=True))
    hot = np.eye(z.shape[-1])[y]
    return Var(np.array(-(weight[..., None] * hot * logp).sum()), [(logits, lambda g: g * weight[..., None] * (np.exp(logp) - hot))])
