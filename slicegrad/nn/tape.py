"""Reverse-mode differentiation of NumPy arrays.

Every operation notes how to send its gradient to its inputs; ``backward`` walks the notes in reverse.
"""

from __future__ import annotations

import numpy as np

from slicegrad.functions.ship import ship_by_value

ship_by_value(__name__)


def _fit(g, shape):
    """Sum a broadcast gradient back to the input's shape."""
    while g.ndim > len(shape):
        g = g.sum(0)
    for axis, n in enumerate(shape):
        if n == 1 and g.shape[axis] != 1:
            g = g.sum(axis, keepdims=True)
    return g


class Var:
    def __init__(self, value, parents=()):
        self.value = np.asarray(value, dtype=np.float64)
        self.parents = parents
        self.grad = None

    @property
    def shape(self):
        return self.value.shape

    def __add__(self, other):
        other = lift(other)
        return Var(self.value + other.value, ((self, lambda g: _fit(g, self.shape)), (other, lambda g: _fit(g, other.shape))))

    def __neg__(self):
        return Var(-self.value, ((self, lambda g: -g),))

    def __sub__(self, other):
        return self + (-lift(other))

    def __mul__(self, other):
        other = lift(other)
        return Var(self.value * other.value, ((self, lambda g: _fit(g * other.value, self.shape)), (other, lambda g: _fit(g * self.value, other.shape))))

    def __truediv__(self, other):
        other = lift(other)
        return Var(self.value / other.value, ((self, lambda g: _fit(g / other.value, self.shape)), (other, lambda g: _fit(-g * self.value / other.value**2, other.shape))))

    def __matmul__(self, other):
        return Var(self.value @ other.value, ((self, lambda g: g @ other.value.T), (other, lambda g: self.value.T @ g)))

    __radd__ = __add__
    __rmul__ = __mul__

    def reshape(self, *shape):
        return Var(self.value.reshape(*shape), ((self, lambda g: g.reshape(self.shape)),))

    def sum(self, axis=None, keepdims=False):
        def back(g):
            if axis is not None and not keepdims:
                g = np.expand_dims(g, axis)
            return np.broadcast_to(g, self.shape).copy()

        return Var(self.value.sum(axis=axis, keepdims=keepdims), ((self, back),))

    def mean(self, axis=None, keepdims=False):
        n = self.value.size if axis is None else np.prod([self.shape[a] for a in np.atleast_1d(axis)])
        return self.sum(axis, keepdims) * (1.0 / n)

    def cut(self, index):
        def back(g):
            out = np.zeros(self.shape)
            out[index] = g
            return out

        return Var(self.value[index], ((self, back),))

    def backward(self):
        order, seen = [], set()

        def visit(v):
            stack = [(v, iter(v.parents))]
            seen.add(id(v))
            while stack:
                node, rest = stack[-1]
                for parent, _ in rest:
                    if id(parent) not in seen:
                        seen.add(id(parent))
                        stack.append((parent, iter(parent.parents)))
                        break
                else:
                    order.append(node)
                    stack.pop()

        visit(self)
        self.grad = np.ones(self.shape)
        for node in reversed(order):
            for parent, back in node.parents:
                g = back(node.grad)
                parent.grad = g if parent.grad is None else parent.grad + g


def lift(x) -> Var:
    return x if isinstance(x, Var) else Var(x)


def _point(value, slope):
    return lambda x: (lambda y: Var(y, ((x, lambda g: g * slope(x.value, y)),)))(value(x.value))


relu = _point(lambda v: np.maximum(v, 0), lambda v, y: v > 0)
tanh = _point(np.tanh, lambda v, y: 1 - y * y)
sigmoid = _point(lambda v: 1 / (1 + np.exp(-np.clip(v, -60, 60))), lambda v, y: y * (1 - y))
sqrt = _point(np.sqrt, lambda v, y: 0.5 / y)
softplus = _point(lambda v: np.maximum(v, 0) + np.log1p(np.exp(-np.abs(v))), lambda v, y: 1 / (1 + np.exp(-np.clip(v, -60, 60))))
absolute = _point(np.abs, lambda v, y: np.sign(v))


def concat(parts, axis):
    at = np.cumsum([0] + [p.shape[axis] for p in parts])
    return Var(np.concatenate([p.value for p in parts], axis), tuple((p, lambda g, a=a, b=b: np.take(g, range(a, b), axis)) for p, a, b in zip(parts, at[:-1], at[1:])))


def gather(table, index):
    """Rows of an embedding table."""
    def back(g):
        rows, g = len(table.value), g.reshape(len(index), -1)
        return np.stack([np.bincount(index, c, rows) for c in g.T], axis=1).reshape(table.shape)

    return Var(table.value[index], ((table, back),))


def log_softmax(x):
    shifted = x.value - x.value.max(-1, keepdims=True)
    y = shifted - np.log(np.exp(shifted).sum(-1, keepdims=True))
    return Var(y, ((x, lambda g: g - np.exp(y) * g.sum(-1, keepdims=True)),))


def _windows(value, kh, kw, pad_h, pad_w):
    padded = np.pad(value, ((0, 0), (pad_h, kh - 1 - pad_h), (pad_w, kw - 1 - pad_w), (0, 0)))
    return np.lib.stride_tricks.sliding_window_view(padded, (kh, kw), axis=(1, 2))  # b h w c kh kw


def conv2d(x, kernel):
    """(b, h, w, c) with (kh, kw, c, o), same size, stride 1."""
    kh, kw, c, o = kernel.shape
    ph, pw = (kh - 1) // 2, (kw - 1) // 2
    cols = _windows(x.value, kh, kw, ph, pw).transpose(0, 1, 2, 4, 5, 3).reshape(*x.shape[:3], kh * kw * c)
    flat = kernel.value.reshape(kh * kw * c, o)

    def to_x(g):
        d = (g @ flat.T).reshape(*x.shape[:3], kh, kw, c)
        out = np.zeros((x.shape[0], x.shape[1] + kh - 1, x.shape[2] + kw - 1, c))
        for i in range(kh):
            for j in range(kw):
                out[:, i : i + x.shape[1], j : j + x.shape[2]] += d[:, :, :, i, j]
        return out[:, ph : ph + x.shape[1], pw : pw + x.shape[2]]

    return Var(cols @ flat, ((x, to_x), (kernel, lambda g: (cols.reshape(-1, kh * kw * c).T @ g.reshape(-1, o)).reshape(kernel.shape))))


def max_pool(x, size):
    b, h, w, c = x.shape
    v = x.value[:, : h // size * size, : w // size * size].reshape(b, h // size, size, w // size, size, c)
    y = v.max((2, 4))
    first = v == y[:, :, None, :, None]
    first = first / first.sum((2, 4), keepdims=True)

    def back(g):
        out = np.zeros(x.shape)
        out[:, : h // size * size, : w // size * size] = (first * g[:, :, None, :, None]).reshape(b, h // size * size, w // size * size, c)
        return out

    return Var(y, ((x, back),))


def mean_pool(x, size):
    b, h, w, c = x.shape
    return x.reshape(b, h // size, size, w // size, size, c).mean((2, 4))


def max_same(x, size):
    """The maximum of every window, stride 1; beyond the edge counts as nothing."""
    pad = size // 2
    padded = np.pad(x.value, ((0, 0), (pad, pad), (pad, pad), (0, 0)), constant_values=-np.inf)
    seen = np.lib.stride_tricks.sliding_window_view(padded, (size, size), axis=(1, 2))
    y = seen.max((4, 5))
    hit = seen == y[..., None, None]
    hit = hit / hit.sum((4, 5), keepdims=True)

    def back(g):
        out = np.zeros(padded.shape)
        for i in range(size):
            for j in range(size):
                out[:, i : i + x.shape[1], j : j + x.shape[2]] += hit[..., i, j] * g
        return out[:, pad : pad + x.shape[1], pad : pad + x.shape[2]]

    return Var(y, ((x, back),))


def max_over(x, axis):
    y = x.value.max(axis, keepdims=True)
    hit = x.value == y
    hit = hit / hit.sum(axis, keepdims=True)
    return Var(y.squeeze(axis), ((x, lambda g: hit * np.expand_dims(g, axis)),))


#: Steps of a recurrence that are kept at once; of longer ones the states between, from which the others are run again.
SPAN = 512


def recurrence(kind, table, wh, index):
    """The last state of an rnn, lstm or gru over ``index`` (b, steps): rows of ``table`` are a word's part of the gates.

    One operation with the backward pass through time written out: a step keeps its gates and its state, and nothing else.
    Rows of the batch stand last, so that a gate of a step is one block.
    """
    (n, steps), (m, wide) = index.shape, wh.shape
    squash = lambda v: 1 / (1 + np.exp(-np.minimum(np.maximum(v, -60), 60)))
    own = [slice(k * m, (k + 1) * m) for k in range(wide // m)]
    by_step, by_word, by_gate = np.ascontiguousarray(index.T), np.ascontiguousarray(table.value.T), np.ascontiguousarray(wh.value.T)
    size = min(steps, SPAN)
    gates, states = np.empty((size, wide, n)), np.zeros((size + 1, m, n))
    more = np.zeros((size + 1, m, n))  # lstm: the cell; gru: what the reset gate lets through, before it
    spans = [(a, min(a + SPAN, steps)) for a in range(0, steps, SPAN)]
    starts = []

    def ahead(first, end):
        for s in range(end - first):
            z, a, h = gates[s], by_word.take(by_step[first + s], 1), states[s]
            b = by_gate @ h
            if kind == "rnn":
                np.tanh(a + b, out=z)
                states[s + 1] = z
            elif kind == "lstm":
                a += b
                a[own[1]] += 1.0
                z[: 3 * m] = squash(a[: 3 * m])
                z[own[3]] = np.tanh(a[own[3]])
                more[s + 1] = z[own[1]] * more[s] + z[own[0]] * z[own[3]]
                states[s + 1] = z[own[2]] * np.tanh(more[s + 1])
            else:
                z[: 2 * m] = squash(a[: 2 * m] + b[: 2 * m])
                more[s] = b[own[2]]
                z[own[2]] = np.tanh(a[own[2]] + z[own[0]] * more[s])
                states[s + 1] = z[own[1]] * h + (1 - z[own[1]]) * z[own[2]]

    for first, end in spans:
        starts.append((states[0].copy(), more[0].copy()))
        ahead(first, end)
        if end < steps:
            states[0], more[0] = states[end - first], more[end - first]

    done = []

    def back(dh):
        """The gradients of ``table`` and ``wh``; a step's gates give way to their gradient."""
        if done:
            return done
        to_table, to_wh, dh, dc = np.zeros(table.shape), np.zeros(wh.shape), dh.T, np.zeros((m, n))
        for (first, end), start in zip(reversed(spans), reversed(starts)):
            if end < steps:  # the last span's are still there
                states[0], more[0] = start
                ahead(first, end)
            for s in range(end - first - 1, -1, -1):
                z, h = gates[s], states[s]
                d = np.empty((wide, n))
                if kind == "rnn":
                    d[:] = dh * (1 - z * z)
                    through, rest = d, 0.0
                elif kind == "lstm":
                    i, f, o, g = (z[k] for k in own)
                    c = np.tanh(more[s + 1])
                    dc += dh * o * (1 - c * c)
                    d[own[0]], d[own[1]], d[own[2]], d[own[3]] = dc * g, dc * more[s], dh * c, dc * i * (1 - g * g)
                    dc = dc * f
                    d[: 3 * m] *= z[: 3 * m] * (1 - z[: 3 * m])
                    through, rest = d, 0.0
                else:
                    r, u, q = (z[k] for k in own)
                    dq = dh * (1 - u) * (1 - q * q)
                    d[own[0]], d[own[1]], d[own[2]] = dq * more[s] * r * (1 - r), dh * (h - q) * u * (1 - u), dq
                    through, rest = d.copy(), dh * u
                    through[own[2]] *= r
                to_wh += h @ through.T
                dh = wh.value @ through + rest
                z[:] = d
            words = by_step[first:end].ravel()
            for k in range(wide):
                to_table[:, k] += np.bincount(words, gates[: end - first, k].ravel(), len(to_table))
        done.extend((to_table, to_wh))
        return done

    return Var(states[spans[-1][1] - spans[-1][0]].T.copy(), ((table, lambda g: back(g)[0]), (wh, lambda g: back(g)[1])))
