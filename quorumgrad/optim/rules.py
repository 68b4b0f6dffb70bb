"""Update rules, learning-rate schedules, parameter averaging and parameter slices."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np

Schedule = Callable[[int], float]


def constant(rate: float) -> Schedule:
    return lambda t: rate


def listed(rates: Sequence[float]) -> Schedule:
    """A rate per update; the last one holds after the list ends."""
    return lambda t: rates[min(t, len(rates) - 1)]


def exponential(rate: float, decay: float, every: float = 1.0, staircase: bool = False) -> Schedule:
    """``rate * decay ** (t / every)``, or in stairs."""
    return lambda t: rate * decay ** (t // every if staircase else t / every)


def stale_safe(schedule: Schedule, lag: float, factor: float = 0.1, from_lag: float = 20) -> Schedule:
    """A lower rate where gradients are ``from_lag`` updates old or more."""
    return (lambda t: factor * schedule(t)) if lag >= from_lag else schedule


@dataclass
class Rule:
    """A first-order rule: ``step`` returns the parameters after one gradient."""

    rate: Schedule
    t: int = 0

    def direction(self, g: np.ndarray) -> np.ndarray:
        return g

    def step(self, theta: np.ndarray, g: np.ndarray) -> np.ndarray:
        out = theta - self.rate(self.t) * self.direction(g)
        self.t += 1
        return out


class Sgd(Rule):
    """The plain step."""


@dataclass
class Momentum(Rule):
    mu: float = 0.9
    velocity: np.ndarray | float = field(default=0.0)

    def direction(self, g):
        self.velocity = self.mu * self.velocity + g
        return self.velocity


@dataclass
class AdaGrad(Rule):
    eps: float = 1e-8
    squares: np.ndarray | float = field(default=0.0)

    def direction(self, g):
        self.squares = self.squares + g**2
        return g / (np.sqrt(self.squares) + self.eps)


@dataclass
class RmsProp(Rule):
    rho: float = 0.9
    eps: float = 1e-8
    mu: float = 0.0
    squares: np.ndarray | float = field(default=0.0)
    velocity: np.ndarray | float = field(default=0.0)

    def direction(self, g):
        self.squares = self.rho * self.squares + (1 - self.rho) * g**2
        self.velocity = self.mu * self.velocity + g / (np.sqrt(self.squares) + self.eps)
        return self.velocity


@dataclass
class Adam(Rule):
    b1: float = 0.9
    b2: float = 0.999
    eps: float = 1e-8
    first: np.ndarray | float = field(default=0.0)
    second: np.ndarray | float = field(default=0.0)

    def direction(self, g):
        self.first = self.b1 * self.first + (1 - self.b1) * g
        self.second = self.b2 * self.second + (1 - self.b2) * g**2
        n = self.t + 1
        return self.first / (1 - self.b1**n) / (np.sqrt(self.second / (1 - self.b2**n)) + self.eps)


RULES: dict[str, type[Rule]] = {"sgd": Sgd, "momentum": Momentum, "adagrad": AdaGrad, "rmsprop": RmsProp, "adam": Adam}


@dataclass
class Ema:
    """Running average of the parameters, fed before each step; it begins at the initial parameters."""

    decay: float
    value: np.ndarray | None = None

    def feed(self, theta: np.ndarray) -> np.ndarray:
        self.value = theta.copy() if self.value is None else self.decay * self.value + (1 - self.decay) * theta
        return self.value


@dataclass(frozen=True)
class ShardPlan:
    """Which server owns which coordinate: contiguous slices of nearly equal size."""

    size: int
    shards: int

    def bounds(self) -> np.ndarray:
        return np.linspace(0, self.size, self.shards + 1).round().astype(int)

    def slices(self) -> list[slice]:
        b = self.bounds()
        return [slice(int(a), int(c)) for a, c in zip(b[:-1], b[1:])]

    def shard_of(self) -> np.ndarray:
        return np.repeat(np.arange(self.shards), np.diff(self.bounds()))
