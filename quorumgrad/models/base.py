"""Models in numpy: mean loss and gradient over a batch of rows.  Parameters are one flat vector; ``layers`` names its slices."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


class Model:
    """What a model offers; ``classes`` is 0 for regression."""

    classes = 0

    def size(self) -> int:
        raise NotImplementedError

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size())

    def layers(self) -> list[slice]:
        """Slices of the parameters from the bottom layer to the top one."""
        return [slice(0, self.size())]

    def loss_and_grad(self, theta: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
        raise NotImplementedError

    def loss(self, theta: np.ndarray, x: np.ndarray, y: np.ndarray) -> float:
        return self.loss_and_grad(theta, x, y)[0]

    def grad(self, theta: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return self.loss_and_grad(theta, x, y)[1]

    def scores(self, theta: np.ndarray, x: np.ndarray) -> np.ndarray:
        """One column per class, or the prediction."""
        raise NotImplementedError

    def predict(self, theta: np.ndarray, x: np.ndarray) -> np.ndarray:
        s = self.scores(theta, x)
        return s if not self.classes else s.argmax(axis=1)

    def predict_all(self, thetas: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Predictions of several vectors of parameters, a row for each."""
        return np.stack([self.predict(theta, x) for theta in thetas])


def log_softmax(z: np.ndarray) -> np.ndarray:
    z = z - z.max(axis=1, keepdims=True)
    return z - np.log(np.exp(z).sum(axis=1, keepdims=True))


@dataclass(frozen=True)
class LinearModel(Model):
    """Least squares: half the mean squared error."""

    dim: int

    def size(self) -> int:
        return self.dim

    def loss_and_grad(self, theta, x, y):
        r = x @ theta - y
        return float(0.5 * (r**2).mean()), x.T @ r / len(y)

    def scores(self, theta, x):
        return x @ theta


@dataclass(frozen=True)
class LogisticModel(Model):
    """Two classes, 0 and 1, with an optional L2 penalty."""

    dim: int
    l2: float = 0.0
    classes: int = 2

    def size(self) -> int:
        return self.dim

    def loss_and_grad(self, theta, x, y):
        z = x @ theta
        loss = np.logaddexp(0, z) - y * z
        p = 0.5 * (1 + np.tanh(z / 2))
        return float(loss.mean() + 0.5 * self.l2 * theta @ theta), x.T @ (p - y) / len(y) + self.l2 * theta

    def scores(self, theta, x):
        z = x @ theta
        return np.stack([-z, z], axis=1)


@dataclass(frozen=True)
class SoftmaxModel(Model):
    """``classes`` classes, one weight row per class and a bias."""

    dim: int
    classes: int
    l2: float = 0.0

    def size(self) -> int:
        return (self.dim + 1) * self.classes

    def scores(self, theta, x):
        w = theta.reshape(self.dim + 1, self.classes)
        return x @ w[:-1] + w[-1]

    def predict_all(self, thetas, x, block: int = 512):
        """One product for all of them, in blocks of rows."""
        w = thetas.reshape(len(thetas), self.dim + 1, self.classes)
        wide, bias = w[:, :-1].transpose(1, 0, 2).reshape(self.dim, -1), w[:, -1].ravel()
        parts = [(x[i : i + block] @ wide + bias).reshape(-1, len(thetas), self.classes).argmax(axis=2) for i in range(0, len(x), block)]
        return np.concatenate(parts).T if parts else np.empty((len(thetas), 0), int)

    def loss_and_grad(self, theta, x, y):
        logp = log_softmax(self.scores(theta, x))
        y = y.astype(int)
        d = np.exp(logp)
        d[np.arange(len(y)), y] -= 1
        d /= len(y)
        grad = np.concatenate([x.T @ d, d.sum(axis=0)[None]]).ravel() + self.l2 * theta
        return float(-logp[np.arange(len(y)), y].mean() + 0.5 * self.l2 * theta @ theta), grad


@dataclass(frozen=True)
class MlpModel(Model):
    """Fully connected layers with tanh between; ``widths`` from the input to the hidden layers, softmax on top."""

    widths: tuple[int, ...]
    classes: int

    def _shapes(self) -> list[tuple[int, int]]:
        full = [*self.widths, self.classes]
        return [(a + 1, b) for a, b in zip(full, full[1:])]

    def size(self) -> int:
        return sum(a * b for a, b in self._shapes())

    def layers(self) -> list[slice]:
        out, at = [], 0
        for a, b in self._shapes():
            out.append(slice(at, at + a * b))
            at += a * b
        return out

    def init(self, seed: int = 0) -> np.ndarray:
        rng = np.random.default_rng(seed)
        parts = []
        for a, b in self._shapes():
            w = rng.normal(size=(a, b)) / np.sqrt(a)
            w[-1] = 0
            parts.append(w.ravel())
        return np.concatenate(parts)

    def _weights(self, theta):
        return [theta[s].reshape(shape) for s, shape in zip(self.layers(), self._shapes(), strict=True)]

    def scores(self, theta, x):
        *hidden, top = self._weights(theta)
        for w in hidden:
            x = np.tanh(x @ w[:-1] + w[-1])
        return x @ top[:-1] + top[-1]

    def loss_and_grad(self, theta, x, y):
        weights, acts = self._weights(theta), [x]
        for w in weights[:-1]:
            acts.append(np.tanh(acts[-1] @ w[:-1] + w[-1]))
        logp = log_softmax(acts[-1] @ weights[-1][:-1] + weights[-1][-1])
        y = y.astype(int)
        d = np.exp(logp)
        d[np.arange(len(y)), y] -= 1
        d /= len(y)
        grads = []
        for w, a in zip(reversed(weights), reversed(acts), strict=True):
            grads.append(np.concatenate([a.T @ d, d.sum(axis=0)[None]]).ravel())
            d = (d @ w[:-1].T) * (1 - a**2)
        return float(-logp[np.arange(len(y)), y].mean()), np.concatenate(grads[::-1])


@dataclass(frozen=True)
class BigramModel(Model):
    """Next symbol given the previous one and a context: a table of logits.  Rows are (context, previous), y the next."""

    contexts: int
    symbols: int

    @property
    def classes(self) -> int:
        return self.symbols

    def size(self) -> int:
        return self.contexts * self.symbols * self.symbols

    def _rows(self, x):
        return x[:, 0].astype(int) * self.symbols + x[:, 1].astype(int)

    def scores(self, theta, x):
        return theta.reshape(-1, self.symbols)[self._rows(x)]

    def loss_and_grad(self, theta, x, y):
        """Columns of ``x`` past the second, if any, weigh the rows (counts)."""
        rows, y = self._rows(x), y.astype(int)
        weight = x[:, 2] if x.shape[1] > 2 else np.ones(len(y))
        total = weight.sum()
        used, where = np.unique(rows, return_inverse=True)  # rows of the table that the batch touches
        logp = log_softmax(theta.reshape(-1, self.symbols)[used])
        d = np.exp(logp) * np.bincount(where, weight, len(used))[:, None]
        np.add.at(d, (where, y), -weight)
        grad = np.zeros((self.contexts * self.symbols, self.symbols))
        grad[used] = d / total
        return float(-(logp[where, y] * weight).sum() / total), grad.ravel()


@dataclass(frozen=True)
class SparseEmbeddingModel(Model):
    """A bag of embedding rows summed to class scores: ``x`` holds (example, token, count) triples, y one label per example."""

    tokens: int
    classes: int

    def size(self) -> int:
        return self.tokens * self.classes

    def scores(self, theta, x):
        table = theta.reshape(self.tokens, self.classes)
        examples, where = np.unique(x[:, 0].astype(int), return_inverse=True)
        rows = table[x[:, 1].astype(int)] * x[:, 2:3]
        return np.stack([np.bincount(where, rows[:, c], len(examples)) for c in range(self.classes)], axis=1)

    def loss_and_grad(self, theta, x, y):
        """The gradient touches the batch's tokens only."""
        logp = log_softmax(self.scores(theta, x))
        d = np.exp(logp)
        d[np.arange(len(y)), y.astype(int)] -= 1
        _, where = np.unique(x[:, 0].astype(int), return_inverse=True)
        grad = np.zeros((self.tokens, self.classes))
        np.add.at(grad, x[:, 1].astype(int), d[where] * x[:, 2:3] / len(y))
        return float(-logp[np.arange(len(y)), y.astype(int)].mean()), grad.ravel()
