"""Element-wise optimizers: each works on a slice of the weights with its own slots, without other slices.

``step(p, it)`` gets a struct column with ``w``, ``g`` and the slots of one element, and the round from 1; it returns
the new struct of ``w`` and slots. ``step_np`` does the same to NumPy arrays, for the single-process reference.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Ops:
    sqrt: object
    absolute: object
    greatest: object
    where: object


SQL = Ops(F.sqrt, F.abs, F.greatest, lambda c, a, b: F.when(c, a).otherwise(b))
NUMPY = Ops(np.sqrt, np.abs, np.maximum, np.where)


@dataclass(frozen=True)
class Optimizer:
    lr: float = 0.1
    slots: tuple = ()
    schedule: object = None

    def rate(self, it: int) -> float:
        return self.lr if self.schedule is None else self.schedule(self.lr, it)

    def rule(self, w, g, s, it, ops):
        raise NotImplementedError

    def step(self, p, it):
        new_w, new_s = self.rule(p["w"], p["g"], [p[k] for k in self.slots], it, SQL)
        lift = lambda v: v if hasattr(v, "_jc") or hasattr(v, "_expr") else F.lit(v)
        return F.struct(lift(new_w).alias("w"), *[lift(v).alias(k) for k, v in zip(self.slots, new_s)])

    def step_np(self, w, g, s, it):
        new_w, new_s = self.rule(w, g, [s[k] for k in self.slots], it, NUMPY)
        return new_w, dict(zip(self.slots, new_s))


@dataclass(frozen=True)
class Sgd(Optimizer):
    decay: float = 0.0

    def rule(self, w, g, s, it, ops):
        return w - (g + w * self.decay) * self.rate(it), []


@dataclass(frozen=True)
class Momentum(Optimizer):
    mu: float = 0.9
    dampening: float = 0.0
    nesterov: bool = False
    slots: tuple = ("u",)

    def rule(self, w, g, s, it, ops):
        u = s[0] * self.mu + g * (1 - self.dampening)
        return w - ((g + u * self.mu) if self.nesterov else u) * self.rate(it), [u]


@dataclass(frozen=True)
class Adagrad(Optimizer):
    eps: float = 1e-8
    slots: tuple = ("s",)

    def rule(self, w, g, s, it, ops):
        total = s[0] + g * g
        return w - g * self.rate(it) / (ops.sqrt(total) + self.eps), [total]


@dataclass(frozen=True)
class RmsProp(Optimizer):
    rho: float = 0.9
    eps: float = 1e-8
    slots: tuple = ("s",)

    def rule(self, w, g, s, it, ops):
        mean = s[0] * self.rho + g * g * (1 - self.rho)
        return w - g * self.rate(it) / (ops.sqrt(mean) + self.eps), [mean]


@dataclass(frozen=True)
class Adadelta(Optimizer):
    rho: float = 0.9
    eps: float = 1e-3
    slots: tuple = ("s", "d")

    def rule(self, w, g, s, it, ops):
        mean = s[0] * self.rho + g * g * (1 - self.rho)
        move = g * ops.sqrt(s[1] + self.eps) / ops.sqrt(mean + self.eps)
        return w - move * self.rate(it), [mean, s[1] * self.rho + move * move * (1 - self.rho)]


@dataclass(frozen=True)
class Adam(Optimizer):
    """``decay`` is decoupled from the gradient (the W variant)."""

    b1: float = 0.9
    b2: float = 0.999
    eps: float = 1e-8
    decay: float = 0.0
    slots: tuple = ("m", "v")

    def rule(self, w, g, s, it, ops):
        m = s[0] * self.b1 + g * (1 - self.b1)
        v = s[1] * self.b2 + g * g * (1 - self.b2)
        move = m / (1 - self.b1**it) / (ops.sqrt(v / (1 - self.b2**it)) + self.eps)
        return w - (move + w * self.decay) * self.rate(it), [m, v]


@dataclass(frozen=True)
class Adamax(Optimizer):
    b1: float = 0.9
    b2: float = 0.999
    eps: float = 1e-8
    slots: tuple = ("m", "v")

    def rule(self, w, g, s, it, ops):
        m = s[0] * self.b1 + g * (1 - self.b1)
        v = ops.greatest(s[1] * self.b2, ops.absolute(g) + self.eps)
        return w - m / v * (self.rate(it) / (1 - self.b1**it)), [m, v]


@dataclass(frozen=True)
class Ftrl(Optimizer):
    l1: float = 0.01
    l2: float = 0.1
    beta: float = 1.0
    slots: tuple = ("z", "n")

    def rule(self, w, g, s, it, ops):
        n = s[1] + g * g
        z = s[0] + g - w * ((ops.sqrt(n) - ops.sqrt(s[1])) / self.rate(it))
        soft = ops.where(z > 0, z - self.l1, z + self.l1)
        return ops.where(ops.absolute(z) <= self.l1, w * 0.0, soft * -1.0 / ((ops.sqrt(n) + self.beta) / self.rate(it) + self.l2)), [z, n]


@dataclass(frozen=True)
class LayerWise(Optimizer):
    """Steps that are scaled by layer: the owner's direction, times a trust that needs norms over all slices of a layer."""

    decay: float = 0.0
    eps: float = 1e-12

    def direction_np(self, w, g, slots, it):
        raise NotImplementedError

    def trust(self, w_norm, u_norm):
        raise NotImplementedError

    def scaled_np(self, w, g, slots, it, trust):
        raise NotImplementedError


@dataclass(frozen=True)
class Lars(LayerWise):
    """Momentum over gradients in parts of the layer's own weights; a layer of zeros takes plain steps."""

    mu: float = 0.9
    eta: float = 0.01
    slots: tuple = ("u",)

    def direction_np(self, w, g, slots, it):
        return g + self.decay * w

    def trust(self, w_norm, u_norm):
        return np.where((w_norm > 0) & (u_norm > 0), self.eta * w_norm / (u_norm + self.eps), 1.0)

    def scaled_np(self, w, g, slots, it, trust):
        u = self.mu * slots["u"] + self.rate(it) * trust * self.direction_np(w, g, slots, it)
        return w - u, {"u": u}


@dataclass(frozen=True)
class Lamb(LayerWise):
    """The same for moments of the gradient."""

    b1: float = 0.9
    b2: float = 0.999
    small: float = 1e-6
    slots: tuple = ("m", "v")

    def moments(self, g, slots):
        return slots["m"] * self.b1 + g * (1 - self.b1), slots["v"] * self.b2 + g * g * (1 - self.b2)

    def direction_np(self, w, g, slots, it):
        m, v = self.moments(g, slots)
        return m / (1 - self.b1**it) / (np.sqrt(v / (1 - self.b2**it)) + self.small) + self.decay * w

    def trust(self, w_norm, u_norm):
        return np.where((w_norm > 0) & (u_norm > 0), w_norm / (u_norm + self.eps), 1.0)

    def scaled_np(self, w, g, slots, it, trust):
        m, v = self.moments(g, slots)
        return w - self.rate(it) * trust * self.direction_np(w, g, slots, it), {"m": m, "v": v}


class Plateau:
    """A schedule that is told each round's loss: after ``patience`` rounds without a better one, the rate falls."""

    def __init__(self, factor: float = 0.5, patience: int = 3, least: float = 0.0):
        self.factor, self.patience, self.least = factor, patience, least
        self.best, self.waited, self.scale = float("inf"), 0, 1.0

    def __call__(self, lr: float, it: int) -> float:
        return lr * self.scale

    def seen(self, loss: float) -> None:
        if loss < self.best - self.least:
            self.best, self.waited = loss, 0
            return
        self.waited += 1
        if self.waited >= self.patience:
            self.scale, self.waited = self.scale * self.factor, 0


class TargetMetric:
    """Stop at a goal: ``evaluate(weights)`` every so many rounds, until it reaches ``goal`` or has not improved for ``patience`` times."""

    def __init__(self, evaluate, goal: float, higher: bool = True, patience: int | None = None, every: int = 1):
        self.evaluate, self.goal, self.sign, self.patience, self.every = evaluate, goal, 1 if higher else -1, patience, every
        self.history: list[float] = []
        self.calls = 0

    def __call__(self, weights) -> bool:
        self.calls += 1
        if self.calls % self.every:
            return False
        self.history.append(float(self.evaluate(weights)))
        own = [self.sign * v for v in self.history]
        if own[-1] >= self.sign * self.goal:
            return True
        return self.patience is not None and len(own) - 1 - max(range(len(own)), key=own.__getitem__) >= self.patience


def step_schedule(every: int, factor: float):
    return lambda lr, it: lr * factor ** ((it - 1) // every)


def multistep_schedule(at: tuple, factor: float):
    return lambda lr, it: lr * factor ** sum(it > k for k in at)


def exponential_schedule(rate: float):
    return lambda lr, it: lr * rate ** (it - 1)


def poly_schedule(total: int, power: float):
    return lambda lr, it: lr * (1 - min(it - 1, total) / total) ** power


def warmup_schedule(rounds: int, then=None):
    return lambda lr, it: lr * it / rounds if it <= rounds else (then(lr, it - rounds) if then else lr)
