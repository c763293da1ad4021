"""Networks of the experiments, small enough for the given tables.

A ``Net`` knows the shapes of its parameters (so their layout in one vector), draws them from a seed, and computes
outputs from (parameters, inputs). ``loss_grad`` gives the summed loss and the gradient over a batch.
"""

from __future__ import annotations

import numpy as np

from slicegrad.functions.ship import ship_by_value
from slicegrad.nn import tape as t

ship_by_value(__name__)


class Net:
    shapes: dict
    loss = "nll"
    frozen: tuple = ()
    #: Rows that are gone through at once; None: the whole batch. Only for networks in which no row depends on another.
    rows: int | None = None
    #: Steps of a sequence; rows may be shorter and are filled up with zeros, those of a piece at a time. None: all rows have one length.
    length: int | None = None

    @property
    def k(self) -> int:
        return sum(int(np.prod(s)) for s in self.shapes.values())

    def init(self, seed: int = 0) -> np.ndarray:
        out = []
        for layer, (name, shape) in enumerate(self.shapes.items()):
            rng = np.random.Generator(np.random.Philox(key=[seed, layer]))
            fan = int(np.prod(shape[:-1])) or 1
            out.append(np.zeros(shape).ravel() if name.endswith(("_b", "_g")) else rng.uniform(-1, 1, shape).ravel() * np.sqrt((1.0 if name.startswith("emb") else 3.0) / (1 if name.startswith("emb") else fan)))
        return np.concatenate(out)

    def params(self, theta: np.ndarray) -> dict:
        out, at = {}, 0
        for name, shape in self.shapes.items():
            n = int(np.prod(shape))
            out[name] = t.Var(theta[at : at + n].reshape(shape))
            at += n
        return out

    def forward(self, p: dict, x: np.ndarray, rng=None):
        raise NotImplementedError

    def gathered(self, rows: np.ndarray) -> np.ndarray:
        """Arrays of a column as the network takes them: a matrix, or as they are where their lengths differ."""
        return np.stack(rows) if self.length is None else rows

    def filled(self, x) -> np.ndarray:
        if self.length is None or isinstance(x, np.ndarray) and x.ndim > 1:
            return np.asarray(x, dtype=np.float64)
        out = np.zeros((len(x), self.length))
        for to, row in zip(out, x):
            to[: len(row)] = row[: self.length]
        return out

    def outputs(self, theta, x):
        p = self.params(theta)
        size = self.rows or max(len(x), 1)
        return np.concatenate([self.forward(p, self.filled(x[a : a + size])).value for a in range(0, max(len(x), 1), size)])

    def loss_grad(self, theta, x, y, seed=(0, 0, 0)):
        if self.rows and len(x) > self.rows:
            loss, g = 0.0, np.zeros(self.k)
            for a in range(0, len(x), self.rows):
                part_loss, part_g = self.loss_grad(theta, x[a : a + self.rows], y[a : a + self.rows], seed)
                loss, g = loss + part_loss, g + part_g
            return loss, g
        p = self.params(theta)
        rng = np.random.Generator(np.random.Philox(key=[seed[0], seed[1] * 1_000_003 + seed[2]]))  # a rerun task draws the same
        out = self.forward(p, self.filled(x), rng)
        loss = CRITERIA[self.loss](out, np.asarray(y, dtype=np.float64))
        loss.backward()
        g = [np.zeros(int(np.prod(s))) if name in self.frozen or p[name].grad is None else p[name].grad.ravel() for name, s in self.shapes.items()]
        return float(loss.value), np.concatenate(g)


def nll(out, y):
    """``out``: log-probabilities; ``y``: classes in the first column."""
    c = y.reshape(len(y), -1)[:, 0].astype(int)
    return -out.cut((np.arange(len(c)), c)).sum()


def mse(out, y):
    d = out.reshape(len(y), -1) - y.reshape(len(y), -1)
    return (d * d).mean(1).sum()


def l1(out, y):
    return t.absolute(out.reshape(len(y), -1) - y.reshape(len(y), -1)).mean(1).sum()


def smooth_l1(out, y):
    d = out.reshape(len(y), -1) - y.reshape(len(y), -1)
    near = np.abs(d.value) < 1
    return (d * d * (0.5 * near) + (t.absolute(d) - 0.5) * (1.0 * ~near)).mean(1).sum()


def bce(out, y):
    """``out``: probabilities."""
    z = out.reshape(-1)
    p = t.Var(np.clip(z.value, 1e-9, 1 - 1e-9), ((z, lambda g: g),))
    y = y.reshape(len(y), -1)[:, 0]
    log = lambda v: t.Var(np.log(v.value), ((v, lambda g: g / v.value),))
    return -(log(p) * y + log(-p + 1.0) * (1 - y)).sum()


def hinge(out, y):
    sign = np.where(y.reshape(len(y), -1)[:, 0] > 0, 1.0, -1.0)
    return t.relu(out.reshape(-1) * -sign + 1.0).sum()


CRITERIA = {"nll": nll, "mse": mse, "l1": l1, "smooth_l1": smooth_l1, "bce": bce, "hinge": hinge}


#: Steps of sequences in the memory of a task at once, some 1 KB each.
STEPS = 100_000
#: Word ids of the rows that a recurrence goes through at once, where it doesn't keep every step.
IDS = 4_000_000


class Mlp(Net):
    def __init__(self, d, hidden, classes):
        self.shapes = {"w1": (d, hidden), "w1_b": (hidden,), "w2": (hidden, classes), "w2_b": (classes,)}

    def forward(self, p, x, rng=None):
        return t.log_softmax(t.relu(t.lift(x) @ p["w1"] + p["w1_b"]) @ p["w2"] + p["w2_b"])


class TextConv(Net):
    """embedding, convolution over time, maximum over time, dense."""

    def __init__(self, vocabulary, length, e, filters, width, classes):
        self.length, self.e, self.width = length, e, width
        self.rows = max(1, STEPS // length)
        self.shapes = {"emb": (vocabulary, e), "c": (1, width, e, filters), "c_b": (filters,), "w": (filters, classes), "w_b": (classes,)}

    def forward(self, p, x, rng=None):
        words = t.gather(p["emb"], x.astype(int).ravel()).reshape(len(x), 1, self.length, self.e)
        h = t.relu(t.conv2d(words, p["c"]) + p["c_b"])
        return t.log_softmax(t.max_over(h.reshape(len(x), self.length, -1), 1) @ p["w"] + p["w_b"])


def batch_norm(v, gamma, beta):
    """Channels brought to mean beta and spread gamma, by the statistics of the task's own batch."""
    axes = tuple(range(len(v.shape) - 1))
    centred = v - v.mean(axes, keepdims=True)
    return centred / t.sqrt((centred * centred).mean(axes, keepdims=True) + 1e-5) * gamma + beta


def each_step(layer, v):
    """A layer applied to every step of a sequence: (b, steps, ...) by way of (b steps, ...)."""
    out = layer(v.reshape(v.shape[0] * v.shape[1], *v.shape[2:]))
    return out.reshape(v.shape[0], v.shape[1], *out.shape[1:])


class Inception(Net):
    """Four branches side by side, joined by channel; ``factored`` uses 1 x n and n x 1 kernels, ``residual`` a bottleneck.

    The last two kinds normalise their batches after every convolution.
    """

    def __init__(self, side, width, classes, kind="inception", dropout=0.1):
        self.side, self.width, self.kind, self.dropout = side, width, kind, dropout
        w = width
        self.shapes = {"stem": (3, 3, 1, w), "stem_b": (w,)}
        if kind == "residual":
            self.shapes |= {"a": (1, 1, w, w // 2), "b": (3, 3, w // 2, w // 2), "c": (1, 1, w // 2, w)} | self._norms(a=w // 2, b=w // 2, c=w)
            out = w
        else:
            five = {"d5": (1, 5, w // 2, w // 2), "d5t": (5, 1, w // 2, w // 2)} if kind == "factored" else {"d5": (5, 5, w // 2, w // 2)}
            self.shapes |= (self._norms(a=w // 2, b1=w // 2, b3=w // 2, d1=w // 2, d5=w // 2, d5t=w // 2, e=w // 2) if kind == "factored" else {}) | {"a": (1, 1, w, w // 2), "b1": (1, 1, w, w // 2), "b3": (3, 3, w // 2, w // 2), "d1": (1, 1, w, w // 2), **five, "e": (1, 1, w, w // 2)}
            out = w // 2 * 4
        self.shapes |= {"head": ((side // 2) ** 2 * out, classes), "head_b": (classes,)}

    @staticmethod
    def _norms(**channels) -> dict:
        return {f"{name}_{part}": (n,) for name, n in channels.items() for part in ("one_g", "zero_b")}

    def _conv(self, p, name, v):
        """A convolution, normalised if it has the parameters for it. Scales are kept as what they add to one."""
        out = t.conv2d(v, p[name])
        return batch_norm(out, p[f"{name}_one_g"] + 1.0, p[f"{name}_zero_b"]) if f"{name}_one_g" in p else out

    def forward(self, p, x, rng=None):
        n = len(x)
        conv = lambda name, v: self._conv(p, name, v)
        h = t.relu(t.conv2d(t.lift(x.reshape(n, self.side, self.side, 1)), p["stem"]) + p["stem_b"])
        if self.kind == "residual":
            h = t.relu(h + conv("c", t.relu(conv("b", t.relu(conv("a", h))))))
        else:
            d = conv("d5", t.relu(conv("d1", h)))
            if self.kind == "factored":
                d = conv("d5t", d)
            pooled = conv("e", t.max_same(h, 3))
            h = t.relu(t.concat([conv("a", h), conv("b3", t.relu(conv("b1", h))), d, pooled], 3))
        h = t.max_pool(h, 2)
        h = h.reshape(n, -1)
        if rng is not None and self.dropout:
            h = h * ((rng.random(h.shape) >= self.dropout) / (1 - self.dropout))
        return t.log_softmax(h @ p["head"] + p["head_b"])


class Recurrent(Net):
    """rnn, lstm or gru over a sequence of word ids, last state to classes."""

    def __init__(self, vocabulary, length, e, hidden, classes, kind="lstm"):
        self.length, self.e, self.hidden, self.kind = length, e, hidden, kind
        self.rows = max(1, min(STEPS // min(length, t.SPAN), IDS // length))
        gates = {"rnn": 1, "lstm": 4, "gru": 3}[kind]
        self.shapes = {"emb": (vocabulary, e), "wx": (e, gates * hidden), "wh": (hidden, gates * hidden), "g_b": (gates * hidden,), "w": (hidden, classes), "w_b": (classes,)}

    def forward(self, p, x, rng=None):
        # a word's part of the gates is the same wherever it stands
        h = t.recurrence(self.kind, p["emb"] @ p["wx"] + p["g_b"], p["wh"], x[:, : self.length].astype(int))
        return t.log_softmax(h @ p["w"] + p["w_b"])


class ConvLstm(Net):
    """Stacked encoder and decoder of convolutional LSTM cells; the decoder feeds on its own frames."""

    loss = "mse"

    def __init__(self, side, channels, past, future, layers=2, size=3):
        self.side, self.channels, self.past, self.future, self.layers = side, channels, past, future, layers
        self.shapes = {}
        for half in ("enc", "dec"):
            for k in range(layers):
                self.shapes[f"{half}{k}"] = (size, size, (1 if k == 0 else channels) + channels, 4 * channels)
                self.shapes[f"{half}{k}_b"] = (4 * channels,)
        self.shapes |= {"out": (1, 1, channels, 1), "out_b": (1,)}

    def forward(self, p, x, rng=None):
        n, s, c = len(x), self.side, self.channels
        frames = x.reshape(n, self.past, s, s, 1)
        zero = t.lift(np.zeros((n, s, s, c)))
        state = [(zero, zero)] * self.layers

        def step(half, v):
            for k in range(self.layers):
                h, m = state[k]
                z = t.conv2d(t.concat([v, h], 3), p[f"{half}{k}"]) + p[f"{half}{k}_b"]
                i, f, o, g = (z.cut((Ellipsis, slice(j * c, (j + 1) * c))) for j in range(4))
                m = t.sigmoid(f + 1.0) * m + t.sigmoid(i) * t.tanh(g)
                v = t.sigmoid(o) * t.tanh(m)
                state[k] = (v, m)
            return v

        for k in range(self.past):
            step("enc", t.lift(frames[:, k]))
        last, out = t.lift(frames[:, -1]), []
        for _ in range(self.future):
            last = last + t.conv2d(step("dec", last), p["out"]) + p["out_b"]
            out.append(last.reshape(n, 1, s * s))
        return t.concat(out, 1)


class NeuMf(Net):
    """x: (user, item). gmf: weighed product of vectors; mlp: tower on both; neumf: both with vectors of their own.

    Vectors start within ``start`` of zero: with large ones the model learns pairs by heart before it learns what is common.
    """

    loss = "bce"
    rows = 100_000

    def __init__(self, users, items, d, tower=8, kind="neumf", start=1.0):
        self.kind, self.start = kind, start
        self.shapes = {}
        if kind in ("gmf", "neumf", "mf"):
            self.shapes |= {"emb_gu": (users, d), "emb_gi": (items, d)}
        if kind in ("mlp", "neumf"):
            self.shapes |= {"emb_mu": (users, d), "emb_mi": (items, d), "w1": (2 * d, tower), "w1_b": (tower,)}
        width = {"gmf": d, "mlp": tower, "neumf": d + tower, "mf": 0}[kind]
        self.shapes |= {"bu_b": (users, 1), "bi_b": (items, 1)} if kind == "mf" else {"w": (width, 1), "w_b": (1,)}

    def init(self, seed=0):
        size = [int(np.prod(s)) for s in self.shapes.values()]
        scale = [self.start if name.startswith("emb") else 1.0 for name in self.shapes]
        return super().init(seed) * np.repeat(scale, size)

    def forward(self, p, x, rng=None):
        u, i = x[:, 0].astype(int), x[:, 1].astype(int)
        parts = []
        if "emb_gu" in p:
            parts.append(t.gather(p["emb_gu"], u) * t.gather(p["emb_gi"], i))
        if "emb_mu" in p:
            parts.append(t.relu(t.concat([t.gather(p["emb_mu"], u), t.gather(p["emb_mi"], i)], 1) @ p["w1"] + p["w1_b"]))
        if self.kind == "mf":
            return t.sigmoid(parts[0].sum(1, keepdims=True) + t.gather(p["bu_b"], u) + t.gather(p["bi_b"], i))
        joint = parts[0] if len(parts) == 1 else t.concat(parts, 1)
        return t.sigmoid(joint @ p["w"] + p["w_b"])


class Detector(Net):
    """Single shot: a backbone, and at every cell of a grid one square anchor with a score and four box shifts.

    Targets are (x0, y0, x1, y1) of one object. The loss is the cross entropy of matched anchors and of the hardest others
    (three for each match), and the smooth distance of the shifts where matched.
    """

    loss = "multibox"

    def __init__(self, side, grid, channels=6):
        self.side, self.grid, self.channels = side, grid, channels
        self.shapes = {"c1": (3, 3, 1, channels), "c1_b": (channels,), "c2": (3, 3, channels, channels), "c2_b": (channels,), "head": (3, 3, channels, 5), "head_b": (5,)}
        self.anchors = boxes(grid, side)

    def forward(self, p, x, rng=None):
        h = t.lift(x.reshape(len(x), self.side, self.side, 1))
        h = h * h
        while h.shape[1] > self.grid * 2:
            h = t.mean_pool(h, 2)
        h = t.relu(t.conv2d(h, p["c1"]) + p["c1_b"])
        h = t.max_pool(h, h.shape[1] // self.grid)
        h = t.relu(t.conv2d(h, p["c2"]) + p["c2_b"])
        return (t.conv2d(h, p["head"]) + p["head_b"]).reshape(len(x), self.grid**2, 5)

    def loss_grad(self, theta, x, y, seed=(0, 0, 0)):
        p = self.params(theta)
        loss = multibox(self.forward(p, np.asarray(x, dtype=np.float64)), np.asarray(y, dtype=np.float64), self.anchors)
        loss.backward()
        return float(loss.value), np.concatenate([np.zeros(int(np.prod(s))) if k in self.frozen or p[k].grad is None else p[k].grad.ravel() for k, s in self.shapes.items()])

    def outputs(self, theta, x):
        """Of each picture the best box after suppression: x0, y0, x1, y1, score."""
        raw = self.forward(self.params(theta), np.asarray(x, dtype=np.float64)).value
        out = []
        for row in raw:
            box, score = decode(self.anchors, row[:, 1:], self.side), 1 / (1 + np.exp(-np.clip(row[:, 0], -60, 60)))
            best = suppress(box, score)[0]
            out.append([*box[best], score[best]])
        return np.array(out)


def encode(anchor: np.ndarray, box: np.ndarray, v0: float = 0.1, v1: float = 0.2) -> np.ndarray:
    """The shifts that ``decode`` turns into ``box``."""
    size = lambda b: np.maximum(b[..., 2:] - b[..., :2], 1e-6)
    middle = lambda b: (b[..., 2:] + b[..., :2]) / 2
    return np.concatenate([(middle(box) - middle(anchor)) / size(anchor) / v0, np.log(size(box) / size(anchor)) / v1], -1)


def multibox(out, y: np.ndarray, anchors: np.ndarray, least: float = 0.5, hard: int = 3):
    """``out``: (b, anchors, 1 + 4). The best anchor of an object is always matched."""
    overlap = np.stack([iou(anchors, b[None])[:, 0] for b in y])
    match = (overlap >= least) | (overlap == overlap.max(1, keepdims=True))
    z = out.cut((Ellipsis, 0))
    sign = np.where(match, 1.0, -1.0)
    cross = t.softplus(z * -sign)
    other = np.where(match, -np.inf, cross.value)
    rank = (-other).argsort(1, kind="stable").argsort(1, kind="stable")
    counted = match | (rank < hard * match.sum(1, keepdims=True))
    shift = out.cut((Ellipsis, slice(1, 5))) - encode(anchors[None], y[:, None])
    near = np.abs(shift.value) < 1
    distance = (shift * shift * (0.5 * near) + (t.absolute(shift) - 0.5) * (1.0 * ~near)) * match[..., None].astype(float)
    return (cross * counted.astype(float)).sum() + distance.sum()


class BitDescriptor(Net):
    """Crop to soft bits; trained to be binary, evenly used and the same for the mirrored crop."""

    loss = "mse"

    def __init__(self, side, bits):
        self.side, self.bits = side, bits
        self.shapes = {"c": (3, 3, 1, 4), "c_b": (4,), "w": (side * side * 4, bits), "w_b": (bits,)}

    def soft(self, p, x):
        n = len(x)
        h = t.relu(t.conv2d(t.lift(x.reshape(n, self.side, self.side, 1)), p["c"]) + p["c_b"])
        return t.tanh(h.reshape(n, -1) @ p["w"] + p["w_b"])

    def forward(self, p, x, rng=None):
        return self.soft(p, x)

    def loss_grad(self, theta, x, y, seed=(0, 0, 0)):
        p = self.params(theta)
        x = np.asarray(x, dtype=np.float64)
        z = self.soft(p, x)
        mirrored = self.soft(p, x.reshape(len(x), self.side, self.side)[:, :, ::-1].reshape(len(x), -1))
        d, even, same = z - np.sign(z.value), z.mean(0), z - mirrored
        loss = (d * d).sum() + (even * even).sum() * float(len(x)) + (same * same).sum()
        loss.backward()
        return float(loss.value), np.concatenate([p[k].grad.ravel() for k in self.shapes])

    def packed(self, theta, x) -> np.ndarray:
        return np.packbits(self.outputs(theta, x) > 0, axis=1)


def boxes(anchors: int, side: int, scale: float = 1.0) -> np.ndarray:
    """Square anchors of an ``anchors`` by ``anchors`` grid: x0, y0, x1, y1."""
    step = side / anchors
    centre = (np.arange(anchors) + 0.5) * step
    y, x = np.meshgrid(centre, centre, indexing="ij")
    half = step * scale / 2
    return np.stack([x - half, y - half, x + half, y + half], -1).reshape(-1, 4)


def decode(anchor: np.ndarray, delta: np.ndarray, side: int, v0: float = 0.1, v1: float = 0.2) -> np.ndarray:
    w, h = anchor[:, 2] - anchor[:, 0], anchor[:, 3] - anchor[:, 1]
    x = anchor[:, 0] + w / 2 + delta[:, 0] * w * v0
    y = anchor[:, 1] + h / 2 + delta[:, 1] * h * v0
    w, h = w * np.exp(delta[:, 2] * v1), h * np.exp(delta[:, 3] * v1)
    return np.clip(np.stack([x - w / 2, y - h / 2, x + w / 2, y + h / 2], -1), 0, side)


def iou(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Of every box of ``a`` with every box of ``b``."""
    low = np.maximum(a[:, None, :2], b[None, :, :2])
    high = np.minimum(a[:, None, 2:], b[None, :, 2:])
    inter = np.prod(np.clip(high - low, 0, None), -1)
    area = lambda v: (v[:, 2] - v[:, 0]) * (v[:, 3] - v[:, 1])
    return inter / np.maximum(area(a)[:, None] + area(b)[None] - inter, 1e-12)


def suppress(box: np.ndarray, score: np.ndarray, most: float = 0.5) -> list[int]:
    """Non-maximum suppression: best first, equals by number."""
    rest = sorted(range(len(score)), key=lambda k: (-score[k], k))
    kept: list[int] = []
    while rest:
        best = rest.pop(0)
        kept.append(best)
        rest = [k for k in rest if iou(box[[best]], box[[k]])[0, 0] <= most]
    return kept
