"""Local losses: value and gradient over a batch, and predictions, with numpy. Parameters are flat vectors."""

from __future__ import annotations

import numpy as np


def _softmax(s: np.ndarray) -> np.ndarray:
    e = np.exp(s - s.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


class Softmax:
    def __init__(self, features: int, classes: int):
        self.shape = (features, classes)
        self.size = features * classes

    def start(self, rng=None) -> np.ndarray:
        return np.zeros(self.size)

    def value_grad(self, w, x, y):
        p = _softmax(x @ w.reshape(self.shape))
        loss = -np.log(np.maximum(p[np.arange(len(y)), y], 1e-300)).mean()
        p[np.arange(len(y)), y] -= 1
        return loss, (x.T @ p / len(y)).ravel()

    def predict(self, w, x):
        return (x @ w.reshape(self.shape)).argmax(1)


class _Margin:
    """Binary losses of label * score, labels 0 and 1."""

    def __init__(self, features: int, classes: int = 2):
        self.size = features

    def start(self, rng=None) -> np.ndarray:
        return np.zeros(self.size)

    def value_grad(self, w, x, y):
        s = 2.0 * y - 1
        v, g = self.margin(s * (x @ w))
        return v.mean(), x.T @ (g * s) / len(y)

    def predict(self, w, x):
        return (x @ w > 0).astype(int)


class Logistic(_Margin):
    @staticmethod
    def margin(m):
        return np.logaddexp(0, -m), -1 / (1 + np.exp(np.clip(m, -500, 500)))


class SmoothHinge(_Margin):
    @staticmethod
    def margin(m):
        return np.where(m >= 1, 0, np.where(m > 0, (1 - m) ** 2 / 2, 0.5 - m)), np.where(m >= 1, 0, np.where(m > 0, m - 1, -1.0))


class LeastSquares(_Margin):
    @staticmethod
    def margin(m):
        return (1 - m) ** 2 / 2, m - 1


class MLP:
    """A dense net with rectified layers; residual adds each equal-sized layer's input to its output."""

    def __init__(self, features: int, classes: int, hidden: tuple[int, ...] = (64, 32), residual: bool = False):
        sizes = [features, *hidden, classes]
        self.shapes, self.residual = list(zip(sizes, sizes[1:], strict=False)), residual
        self.size = sum(a * b for a, b in self.shapes)

    def start(self, rng=None) -> np.ndarray:
        rng = rng or np.random.default_rng(0)
        return np.concatenate([rng.normal(0, (2 / a) ** 0.5, a * b) for a, b in self.shapes])

    def _layers(self, w):
        out, at = [], 0
        for a, b in self.shapes:
            out.append(w[at : at + a * b].reshape(a, b))
            at += a * b
        return out

    def _forward(self, w, x):
        acts = [x]
        layers = self._layers(w)
        for i, m in enumerate(layers[:-1]):
            h = np.maximum(acts[-1] @ m, 0)
            acts.append(h + acts[-1] if self._skips(i) else h)
        return layers, acts, acts[-1] @ layers[-1]

    def _skips(self, i):
        return self.residual and self.shapes[i][0] == self.shapes[i][1]

    def value_grad(self, w, x, y):
        layers, acts, s = self._forward(w, x)
        p = _softmax(s)
        loss = -np.log(np.maximum(p[np.arange(len(y)), y], 1e-300)).mean()
        p[np.arange(len(y)), y] -= 1
        back, grads = p / len(y), []
        for i in range(len(layers) - 1, -1, -1):
            if i < len(layers) - 1:
                through = back * (acts[i] @ layers[i] > 0)
                grads.append(acts[i].T @ through)
                back = through @ layers[i].T + (back if self._skips(i) else 0)
            else:
                grads.append(acts[i].T @ back)
                back = back @ layers[i].T
        return loss, np.concatenate([g.ravel() for g in reversed(grads)])

    def predict(self, w, x):
        return self._forward(w, x)[2].argmax(1)


def residual_mlp(features: int, classes: int) -> MLP:
    return MLP(features, classes, (32, 32, 32), residual=True)


LOSSES = {"softmax": Softmax, "logistic": Logistic, "hinge": SmoothHinge, "least_squares": LeastSquares, "mlp3": MLP, "residual_mlp": residual_mlp}
