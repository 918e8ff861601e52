"""Small networks with hand-written reverse mode, and the optimiser that trains them."""

from __future__ import annotations

import math

import numpy as np

from ..operators.maps import ACTIVATIONS, act_gradient


class Layer:
    def params(self) -> dict[str, np.ndarray]:
        return {}

    def forward(self, x: np.ndarray, training: bool = False) -> np.ndarray:
        raise NotImplementedError

    def backward(self, g: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    grads: dict[str, np.ndarray]

    def lipschitz(self) -> float:
        raise NotImplementedError


class Affine(Layer):
    def __init__(self, n_in: int, n_out: int, rng: np.random.Generator, gain: float = 1.0):
        self.w = rng.standard_normal((n_in, n_out)) * gain / math.sqrt(n_in)
        self.b = np.zeros(n_out)

    def params(self):
        return {"w": self.w, "b": self.b}

    def forward(self, x, training=False):
        self.x = x
        return x @ self.w + self.b

    def backward(self, g):
        self.grads = {"w": self.x.T @ g, "b": g.sum(0)}
        return g @ self.w.T

    def lipschitz(self):
        return float(np.linalg.norm(self.w, 2))


class Activation(Layer):
    LIP = {"relu": 1.0, "tanh": 1.0, "cos": 1.0, "sin": 1.0, "identity": 1.0, "sigmoid": 0.25, "gelu": 1.13}

    def __init__(self, kind: str):
        self.kind = kind

    def forward(self, x, training=False):
        self.x = x
        return ACTIVATIONS[self.kind](x)

    def backward(self, g):
        self.grads = {}
        return g * act_gradient(self.kind, self.x)

    def lipschitz(self):
        return self.LIP[self.kind]


class BatchNorm(Layer):
    """Batch statistics while training; stored ones otherwise, so inference is a row-wise map and sketches stay additive."""

    def __init__(self, n: int):
        self.gamma, self.beta = np.ones(n), np.zeros(n)
        self.mean, self.var = np.zeros(n), np.ones(n)

    def params(self):
        return {"gamma": self.gamma, "beta": self.beta}

    def forward(self, x, training=False):
        self.training = training
        if training:
            m, v = x.mean(0), x.var(0)
            self.mean, self.var = 0.9 * self.mean + 0.1 * m, 0.9 * self.var + 0.1 * v
        else:
            m, v = self.mean, self.var
        self.inv = 1 / np.sqrt(v + 1e-5)
        self.h = (x - m) * self.inv
        return self.h * self.gamma + self.beta

    def backward(self, g):
        self.grads = {"gamma": (g * self.h).sum(0), "beta": g.sum(0)}
        gh = g * self.gamma
        if not self.training:
            return gh * self.inv
        return self.inv * (gh - gh.mean(0) - self.h * (gh * self.h).mean(0))

    def lipschitz(self):
        return float(np.abs(self.gamma / np.sqrt(self.var + 1e-5)).max())


class LayerNorm(Layer):
    FLOOR = 1e-5

    def __init__(self, n: int):
        self.gamma, self.beta = np.ones(n), np.zeros(n)

    def params(self):
        return {"gamma": self.gamma, "beta": self.beta}

    def forward(self, x, training=False):
        self.inv = 1 / np.sqrt(x.var(1, keepdims=True) + self.FLOOR)
        self.h = (x - x.mean(1, keepdims=True)) * self.inv
        return self.h * self.gamma + self.beta

    def backward(self, g):
        self.grads = {"gamma": (g * self.h).sum(0), "beta": g.sum(0)}
        gh = g * self.gamma
        return self.inv * (gh - gh.mean(1, keepdims=True) - self.h * (gh * self.h).mean(1, keepdims=True))

    def lipschitz(self):
        """With the variance floor: vacuous in practice, but finite."""
        return float(np.abs(self.gamma).max() / math.sqrt(self.FLOOR))


class Chain(Layer):
    def __init__(self, *layers: Layer):
        self.layers = layers

    def params(self):
        return {f"{i}.{k}": v for i, x in enumerate(self.layers) for k, v in x.params().items()}

    def forward(self, x, training=False):
        for layer in self.layers:
            x = layer.forward(x, training)
        return x

    def backward(self, g):
        self.grads = {}
        for i in range(len(self.layers) - 1, -1, -1):
            g = self.layers[i].backward(g)
            self.grads |= {f"{i}.{k}": v for k, v in self.layers[i].grads.items()}
        return g

    def lipschitz(self):
        return math.prod(x.lipschitz() for x in self.layers)

    def arrays(self) -> dict[str, np.ndarray]:
        out = dict(self.params())
        todo = [("", self)]
        while todo:
            name, layer = todo.pop()
            if isinstance(layer, BatchNorm):
                out |= {f"{name}mean": layer.mean, f"{name}var": layer.var}
            for i, x in enumerate(getattr(layer, "layers", ()) or ([layer.branch] if isinstance(layer, Residual) else [])):
                todo.append((f"{name}{i}.", x))
        return out


class Residual(Layer):
    def __init__(self, branch: Chain):
        self.branch = branch

    def params(self):
        return self.branch.params()

    def forward(self, x, training=False):
        return x + self.branch.forward(x, training)

    def backward(self, g):
        out = g + self.branch.backward(g)
        self.grads = self.branch.grads
        return out

    def lipschitz(self):
        return 1 + self.branch.lipschitz()


def residual_mlp(d: int, m: int, style: str = "bn_relu", blocks: int = 2, hidden: int = 32, head: str = "none", seed: int = 0) -> Chain:
    """Input to width `hidden`, residual blocks, output. bn_relu: normalise, relu, affine, twice; ln_gelu: normalise, affine, gelu, affine."""
    rng = np.random.Generator(np.random.Philox(seed))
    layers: list[Layer] = [Affine(d, hidden, rng)]
    for _ in range(blocks):
        if style == "bn_relu":
            branch = Chain(BatchNorm(hidden), Activation("relu"), Affine(hidden, hidden, rng), BatchNorm(hidden), Activation("relu"), Affine(hidden, hidden, rng, 0.5))
        elif style == "ln_gelu":
            branch = Chain(LayerNorm(hidden), Affine(hidden, hidden, rng), Activation("gelu"), Affine(hidden, hidden, rng, 0.5))
        else:
            raise ValueError(style)
        layers.append(Residual(branch))
    layers.append(Affine(hidden, m, rng))
    if head != "none":
        layers.append(Activation(head))
    return Chain(*layers)


def set_params(net: Layer, values: dict[str, np.ndarray]) -> None:
    for k, v in net.params().items():
        v[...] = values[k]


class Adam:
    def __init__(self, rate: float = 3e-5, schedule: str = "constant", total: int = 0, patience: int = 20):
        self.rate, self.schedule, self.total, self.patience = rate, schedule, total, patience
        self.t, self.state, self.best, self.waited, self.factor = 0, {}, math.inf, 0, 1.0

    def current(self) -> float:
        if self.schedule == "cosine" and self.total:
            return self.rate * 0.5 * (1 + math.cos(math.pi * min(1.0, self.t / self.total)))
        if self.schedule == "step" and self.total:
            return self.rate * 0.1 ** (3 * self.t // max(self.total, 1))
        return self.rate * self.factor

    def observe(self, loss: float) -> None:
        """For the plateau schedule: halve the rate after `patience` observations without a better loss."""
        if loss < self.best * (1 - 1e-4):
            self.best, self.waited = loss, 0
        else:
            self.waited += 1
            if self.schedule == "plateau" and self.waited >= self.patience:
                self.factor, self.waited = self.factor / 2, 0

    def update(self, params: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        rate = self.current()
        for k, p in params.items():
            g = grads[k]
            m, s = self.state.get(k, (0.0, 0.0))
            m, s = 0.9 * m + 0.1 * g, 0.999 * s + 0.001 * g * g
            self.state[k] = (m, s)
            p -= rate * (m / (1 - 0.9**self.t)) / (np.sqrt(s / (1 - 0.999**self.t)) + 1e-8)
