"""Derivative-free search over mixed vectors: continuous coordinates and choices (argmax of free coordinates)."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np


@dataclass(frozen=True)
class Space:
    """names of continuous coordinates with their start values and spreads, and choices by name."""

    start: dict[str, float]
    spread: dict[str, float]
    choices: dict[str, Sequence] = field(default_factory=dict)
    block: int = 0  # free weights without a name, start 0 and spread 1

    @property
    def dim(self) -> int:
        return len(self.start) + sum(len(c) for c in self.choices.values()) + self.block

    def read(self, x: np.ndarray) -> dict:
        out: dict = {k: self.start[k] + self.spread[k] * x[i] for i, k in enumerate(self.start)}
        at = len(self.start)
        for k, c in self.choices.items():
            out[k] = c[int(np.argmax(x[at : at + len(c)]))]
            at += len(c)
        out["block"] = x[at:]
        return out


class Strategy:
    """ask() gives a generation of points, tell() takes their losses; the least loss so far is kept."""

    def __init__(self, dim: int, seed: int = 0, size: int = 8):
        self.dim, self.size = dim, size
        self.rng = np.random.Generator(np.random.Philox(seed))
        self.best_x, self.best = np.zeros(dim), math.inf
        self.history: list[float] = []

    def ask(self) -> np.ndarray:
        raise NotImplementedError

    def tell(self, xs: np.ndarray, losses: Sequence[float]) -> None:
        i = int(np.argmin(losses))
        if losses[i] < self.best:
            self.best, self.best_x = float(losses[i]), xs[i].copy()
        self.history.append(self.best)
        self.learn(xs, np.asarray(losses, dtype=float))

    def learn(self, xs: np.ndarray, losses: np.ndarray) -> None:
        pass


class RandomSearch(Strategy):
    def ask(self):
        return self.rng.standard_normal((self.size, self.dim))


class OneFifth(Strategy):
    """One parent; the step grows when more than a fifth of the children are better."""

    def __init__(self, dim, seed=0, size=4):
        super().__init__(dim, seed, size)
        self.x, self.fx, self.sigma = np.zeros(dim), math.inf, 0.5

    def ask(self):
        return self.x + self.sigma * self.rng.standard_normal((self.size, self.dim))

    def learn(self, xs, losses):
        share = float(np.mean(losses < self.fx))
        i = int(np.argmin(losses))
        if losses[i] < self.fx:
            self.x, self.fx = xs[i], losses[i]
        self.sigma *= math.exp((share - 0.2) / math.sqrt(self.dim + 1) * 2)


class DifferentialEvolution(Strategy):
    def __init__(self, dim, seed=0, size=12):
        super().__init__(dim, seed, size)
        self.pop, self.loss = self.rng.standard_normal((size, dim)), None

    def ask(self):
        if self.loss is None:
            self.trial = self.pop
            return self.pop
        n, best = self.size, self.pop[int(np.argmin(self.loss))]
        self.trial = self.pop.copy()
        for i in range(n):
            a, b = self.rng.choice(n, 2, replace=False)
            mutant = self.pop[i] + 0.8 * (best - self.pop[i]) + 0.8 * (self.pop[a] - self.pop[b])
            cross = self.rng.random(self.dim) < 0.5
            cross[self.rng.integers(self.dim)] = True
            self.trial[i] = np.where(cross, mutant, self.pop[i])
        return self.trial

    def learn(self, xs, losses):
        if self.loss is None:
            self.loss = losses.copy()
            return
        better = losses <= self.loss
        self.pop[better], self.loss[better] = xs[better], losses[better]


class DiagonalEvolution(Strategy):
    """Weighted recombination with a diagonal covariance."""

    def __init__(self, dim, seed=0, size=0):
        super().__init__(dim, seed, size or 4 + int(3 * math.log(dim + 1)))
        self.mean, self.sigma, self.c = np.zeros(dim), 0.5, np.ones(dim)
        self.ps = np.zeros(dim)

    def ask(self):
        return self.mean + self.sigma * np.sqrt(self.c) * self.rng.standard_normal((self.size, self.dim))

    def learn(self, xs, losses):
        mu = self.size // 2
        w = math.log(mu + 0.5) - np.log(np.arange(1, mu + 1))
        w /= w.sum()
        top = xs[np.argsort(losses, kind="stable")[:mu]]
        steps = (top - self.mean) / self.sigma
        y = w @ steps
        mueff = 1 / (w**2).sum()
        cs = (mueff + 2) / (self.dim + mueff + 5)
        self.ps = (1 - cs) * self.ps + math.sqrt(cs * (2 - cs) * mueff) * y / np.sqrt(self.c)
        rate = min(1.0, (self.dim + 2) / 3 * 2 / ((self.dim + 1.3) ** 2 + mueff) * 3)
        self.mean = self.mean + self.sigma * y
        self.c = np.maximum((1 - rate) * self.c + rate * (w @ steps**2), 1e-12)
        self.sigma *= math.exp(min(1.0, cs * (np.linalg.norm(self.ps) / math.sqrt(self.dim) - 1)))


STRATEGIES = {"random": RandomSearch, "one_fifth": OneFifth, "differential": DifferentialEvolution, "diagonal": DiagonalEvolution}


def pick_strategy(dim: int, budget: int, parallel: int = 1) -> str:
    if budget < 4 * dim and budget < 60:
        return "one_fifth"
    if dim <= 50 and budget >= 20 * dim:
        return "diagonal"
    return "differential" if parallel > 1 or budget < 20 * dim else "diagonal"


def derivative_free_search(space: Space, objective: Callable[[dict, int], float] | Callable[[list[dict], int], list[float]], budget: int, strategy: str = "auto", seed: int = 0, batched: bool = False) -> tuple[dict, Strategy]:
    """The first tenth of the budget is random. All candidates of a generation get the same generation number as their seed (common random numbers).

    batched: the objective takes a whole generation, so that Spark can run candidates x datasets in parallel.
    """
    name = pick_strategy(space.dim, budget) if strategy == "auto" else strategy
    tool = STRATEGIES[name](space.dim, seed)
    first = RandomSearch(space.dim, seed + 1, max(1, budget // 10))
    spent, generation = 0, 0
    while spent < budget:
        xs = first.ask() if generation == 0 and name != "random" else tool.ask()
        points = [space.read(x) for x in xs]
        losses = objective(points, generation) if batched else [objective(p, generation) for p in points]
        losses = [x if math.isfinite(x) else 1e300 for x in losses]
        if generation == 0 and name != "random":
            i = int(np.argmin(losses))
            tool.best, tool.best_x = float(losses[i]), xs[i].copy()
            for attribute in ("mean", "x"):
                if hasattr(tool, attribute):
                    setattr(tool, attribute, xs[i].copy())
            tool.history.append(tool.best)
        else:
            tool.tell(xs, losses)
        spent += len(xs)
        generation += 1
    return space.read(tool.best_x), tool
