"""Losses as Column expressions: value and derivative in the score. Scores are doubles, or arrays for several classes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def sigmoid(s: Column) -> Column:
    """Without overflow for large |s|."""
    e = F.exp(-F.abs(s))
    return F.when(s >= 0, 1.0 / (1.0 + e)).otherwise(e / (1.0 + e))


def softplus(s: Column) -> Column:
    """log(1 + exp(s))."""
    return F.log1p(F.exp(-F.abs(s))) + F.greatest(s, F.lit(0.0))


def logsumexp(s: Column) -> Column:
    top = F.array_max(s)
    return top + F.log(F.aggregate(s, F.lit(0.0), lambda acc, x: acc + F.exp(x - top)))


def softmax(s: Column) -> Column:
    z = logsumexp(s)
    return F.transform(s, lambda x: F.exp(x - z))


class Loss:
    """``value(s, y)`` and ``derivative(s, y)``; k scores an example. Losses with ``arrays`` also have both for NumPy arrays, ``value_of``
    and ``derivative_of``, with scores as (k, examples)."""

    k = 1
    arrays = False

    def value(self, s: Column, y: Column) -> Column:
        raise NotImplementedError

    def derivative(self, s: Column, y: Column) -> Column:
        raise NotImplementedError


@dataclass
class Squared(Loss):
    half: bool = False

    def value(self, s, y):
        return (s - y) * (s - y) * (0.5 if self.half else 1.0)

    def derivative(self, s, y):
        return (s - y) * (1.0 if self.half else 2.0)

    arrays = True

    def value_of(self, s, y):
        return (s[0] - y) * (s[0] - y) * (0.5 if self.half else 1.0)

    def derivative_of(self, s, y):
        return (s - y) * (1.0 if self.half else 2.0)


@dataclass
class Quantile(Loss):
    """Pinball loss; at a zero residual the subgradient 0."""

    tau: float = 0.5

    def value(self, s, y):
        r = y - s
        return F.when(r >= 0, r * self.tau).otherwise(r * (self.tau - 1.0))

    def derivative(self, s, y):
        r = y - s
        return F.when(r > 0, F.lit(-self.tau)).when(r < 0, F.lit(1.0 - self.tau)).otherwise(0.0)

    arrays = True

    def value_of(self, s, y):
        r = y - s[0]
        return np.where(r >= 0, r * self.tau, r * (self.tau - 1.0))

    def derivative_of(self, s, y):
        r = y - s
        return np.where(r > 0, -self.tau, np.where(r < 0, 1.0 - self.tau, 0.0))


@dataclass
class Logistic(Loss):
    """Labels 0/1, or -1/+1 with ``labels='pm'``."""

    labels: str = "01"

    def _one(self, y):
        return y if self.labels == "01" else (y + 1.0) / 2.0

    def value(self, s, y):
        return softplus(s) - self._one(y) * s

    def derivative(self, s, y):
        return sigmoid(s) - self._one(y)

    arrays = True

    def value_of(self, s, y):
        return np.logaddexp(0.0, s[0]) - self._one(y) * s[0]

    def derivative_of(self, s, y):
        e = np.exp(-np.abs(s))
        return np.where(s >= 0, 1.0, e) / (1.0 + e) - self._one(y)


@dataclass
class Softmax(Loss):
    """y is a class number, or, with ``targets``, an array of (class, weight) structs."""

    k: int = 2
    targets: bool = False

    def mass(self, y: Column) -> Column:
        """Target weight of each class."""
        if not self.targets:
            return F.transform(F.sequence(F.lit(0), F.lit(self.k - 1)), lambda c: (c == y.cast("int")).cast("double"))
        return F.transform(F.sequence(F.lit(0), F.lit(self.k - 1)), lambda c: F.aggregate(y, F.lit(0.0), lambda acc, t: acc + F.when(t["class"] == c, t["weight"]).otherwise(0.0)))

    def value(self, s, y):
        z = logsumexp(s)
        if not self.targets:
            return z - s[y.cast("int")]
        return F.aggregate(F.zip_with(self.mass(y), s, lambda m, x: m * (z - x)), F.lit(0.0), lambda acc, x: acc + x)

    def derivative(self, s, y):
        m = self.mass(y)
        total = F.aggregate(m, F.lit(0.0), lambda acc, x: acc + x)
        return F.zip_with(softmax(s), m, lambda p, w: total * p - w)

    @property
    def arrays(self) -> bool:
        return not self.targets

    def value_of(self, s, y):
        top = s.max(0)
        return top + np.log(np.exp(s - top).sum(0)) - s[y.astype(int), np.arange(len(y))]

    def derivative_of(self, s, y):
        p = np.exp(s - s.max(0))
        p /= p.sum(0)
        p[y.astype(int), np.arange(len(y))] -= 1.0
        return p


@dataclass
class Pairwise(Loss):
    """-log sigmoid of (score of the positive - score of the negative); s is that difference, y is not used."""

    n_neg: int = 1

    def value(self, s, y=None):
        return softplus(-s)

    def derivative(self, s, y=None):
        return -sigmoid(-s)


@dataclass
class Custom(Loss):
    """A user's loss from two functions of (score, label)."""

    value_fn: Callable[[Column, Column], Column] = None
    derivative_fn: Callable[[Column, Column], Column] = None

    def value(self, s, y):
        return self.value_fn(s, y)

    def derivative(self, s, y):
        return self.derivative_fn(s, y)


def huber(width: float = 1.0) -> Custom:
    """Example of a user's loss."""
    return Custom(
        lambda s, y: F.when(F.abs(s - y) <= width, 0.5 * (s - y) * (s - y)).otherwise(width * (F.abs(s - y) - 0.5 * width)),
        lambda s, y: F.greatest(F.lit(-width), F.least(F.lit(width), s - y)),
    )
