"""Vector losses with gradients and Hessians over batches of scores (rows x outputs)."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

EPS = 1e-15


def softmax(s: np.ndarray) -> np.ndarray:
    e = np.exp(s - s.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def sigmoid(s: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(s, -500, 500)))


def codewords(c: int, kind: str) -> np.ndarray:
    """Rows: the code of each class. onehot; centered (1 and -1/(c-1)); simplex (unit vectors of equal angles, in c dimensions)."""
    one = np.eye(c)
    if kind == "onehot" or c == 1:
        return one
    if kind == "centered":
        return one * (1 + 1 / (c - 1)) - 1 / (c - 1)
    return (one - 1 / c) / np.sqrt(1 - 1 / c)


class Loss:
    """value: per row; grad: rows x C; diag: rows x C; full: rows x C x C. y: labels (rows) or targets (rows x C)."""

    kind = "class"

    def value(self, s, y):
        raise NotImplementedError

    def grad(self, s, y):
        raise NotImplementedError

    def full(self, s, y):
        raise NotImplementedError

    def diag(self, s, y):
        return np.einsum("ijj->ij", self.full(s, y)).copy()

    def predict(self, s):
        """What scores say: class probabilities or values."""
        return softmax(s)


class SoftmaxXent(Loss):
    def value(self, s, y):
        return -np.log(np.maximum(softmax(s)[np.arange(len(s)), y], EPS))

    def grad(self, s, y):
        p = softmax(s)
        p[np.arange(len(s)), y] -= 1
        return p

    def diag(self, s, y):
        p = softmax(s)
        return p * (1 - p)

    def full(self, s, y):
        p = softmax(s)
        h = -p[:, :, None] * p[:, None, :]
        k = np.arange(s.shape[1])
        h[:, k, k] += p
        return h


class Diagonal(Loss):
    """A loss that is a sum over outputs."""

    def full(self, s, y):
        d = self.diag(s, y)
        h = np.zeros((*d.shape, d.shape[1]))
        k = np.arange(d.shape[1])
        h[:, k, k] = d
        return h


class SquaredError(Diagonal):
    kind = "real"

    def value(self, s, y):
        return 0.5 * ((s - y) ** 2).sum(axis=1)

    def grad(self, s, y):
        return s - y

    def diag(self, s, y):
        return np.ones_like(s)

    def predict(self, s):
        return s


class MultiLabelLogistic(Diagonal):
    kind = "multi"

    def value(self, s, y):
        p = np.clip(sigmoid(s), EPS, 1 - EPS)
        return -(y * np.log(p) + (1 - y) * np.log(1 - p)).sum(axis=1)

    def grad(self, s, y):
        return sigmoid(s) - y

    def diag(self, s, y):
        p = sigmoid(s)
        return p * (1 - p)

    def predict(self, s):
        return sigmoid(s)


class Logistic(MultiLabelLogistic):
    """One score; y of 0 and 1, of any shape."""

    kind = "binary"

    def _y(self, y):
        return np.asarray(y, np.float64).reshape(-1, 1)

    def value(self, s, y):
        return super().value(s, self._y(y))

    def grad(self, s, y):
        return super().grad(s, self._y(y))

    def diag(self, s, y):
        return super().diag(s, self._y(y))


class MultiExp(Loss):
    """exp(-u.s / C) with u the code of the label."""

    def __init__(self, code: np.ndarray):
        self.code = code

    def _u(self, s, y):
        u = self.code[y] / s.shape[1]
        return u, np.exp(-(u * s).sum(axis=1))

    def value(self, s, y):
        return self._u(s, y)[1]

    def grad(self, s, y):
        u, e = self._u(s, y)
        return -u * e[:, None]

    def diag(self, s, y):
        u, e = self._u(s, y)
        return u * u * e[:, None]

    def full(self, s, y):
        u, e = self._u(s, y)
        return u[:, :, None] * u[:, None, :] * e[:, None, None]


class MarginExp(Loss):
    """Sum over wrong classes k of exp(-(s . (v_y - v_k)) / 2), v the codewords."""

    def __init__(self, code: np.ndarray):
        self.code = code

    def _terms(self, s, y):
        d = (self.code[y][:, None, :] - self.code[None, :, :]) / 2
        e = np.exp(-np.einsum("ikc,ic->ik", d, s))
        e[np.arange(len(s)), y] = 0
        return d, e

    def value(self, s, y):
        return self._terms(s, y)[1].sum(axis=1)

    def grad(self, s, y):
        d, e = self._terms(s, y)
        return -np.einsum("ik,ikc->ic", e, d)

    def full(self, s, y):
        d, e = self._terms(s, y)
        return np.einsum("ik,ika,ikb->iab", e, d, d)

    def predict(self, s):
        return softmax(s @ self.code.T)


class ZeroSum(Loss):
    """A base loss and mu/2 times the squared sum of the scores."""

    def __init__(self, base: Loss, mu: float):
        self.base, self.mu, self.kind = base, mu, base.kind

    def value(self, s, y):
        return self.base.value(s, y) + self.mu / 2 * s.sum(axis=1) ** 2

    def grad(self, s, y):
        return self.base.grad(s, y) + self.mu * s.sum(axis=1, keepdims=True)

    def diag(self, s, y):
        return self.base.diag(s, y) + self.mu

    def full(self, s, y):
        return self.base.full(s, y) + self.mu

    def predict(self, s):
        return self.base.predict(s)


class HyperDual:
    """a + b e1 + c e2 + d e1 e2 with e1^2 = e2^2 = 0: exact first and second derivatives of array code."""

    __array_priority__ = 100

    def __init__(self, a, b=0.0, c=0.0, d=0.0):
        self.a, self.b, self.c, self.d = a, b, c, d

    def _with(self, f, f1, f2):
        return HyperDual(f, f1 * self.b, f1 * self.c, f1 * self.d + f2 * self.b * self.c)

    @staticmethod
    def of(x):
        return x if isinstance(x, HyperDual) else HyperDual(x)

    def __add__(self, o):
        o = HyperDual.of(o)
        return HyperDual(self.a + o.a, self.b + o.b, self.c + o.c, self.d + o.d)

    __radd__ = __add__

    def __neg__(self):
        return HyperDual(-self.a, -self.b, -self.c, -self.d)

    def __sub__(self, o):
        return self + -HyperDual.of(o)

    def __rsub__(self, o):
        return HyperDual.of(o) - self

    def __mul__(self, o):
        o = HyperDual.of(o)
        return HyperDual(self.a * o.a, self.a * o.b + self.b * o.a, self.a * o.c + self.c * o.a, self.a * o.d + self.d * o.a + self.b * o.c + self.c * o.b)

    __rmul__ = __mul__

    def __truediv__(self, o):
        return self * HyperDual.of(o) ** -1

    def __rtruediv__(self, o):
        return HyperDual.of(o) * self**-1

    def __pow__(self, k):
        return self._with(self.a**k, k * self.a ** (k - 1), k * (k - 1) * self.a ** (k - 2))

    def exp(self):
        e = np.exp(self.a)
        return self._with(e, e, e)

    def log(self):
        return self._with(np.log(self.a), 1 / self.a, -1 / self.a**2)

    def tanh(self):
        t = np.tanh(self.a)
        return self._with(t, 1 - t * t, -2 * t * (1 - t * t))

    def sqrt(self):
        r = np.sqrt(self.a)
        return self._with(r, 0.5 / r, -0.25 / r**3)


def exp(x):
    return x.exp() if isinstance(x, HyperDual) else np.exp(x)


def log(x):
    return x.log() if isinstance(x, HyperDual) else np.log(x)


def sqrt(x):
    return x.sqrt() if isinstance(x, HyperDual) else np.sqrt(x)


class AutoDiff(Loss):
    """A loss given by its value alone: fn(list of C score columns, y) with +, -, *, /, ** and exp, log, sqrt of
    this module. Gradient and Hessian come from hyper-dual numbers, exact to rounding."""

    def __init__(self, fn: Callable, kind: str = "class", predict: Callable = softmax):
        self.fn, self.kind, self._predict = fn, kind, predict

    def value(self, s, y):
        return np.asarray(self.fn([s[:, k] for k in range(s.shape[1])], y))

    def _second(self, s, y, a, b):
        v = [HyperDual(s[:, k], float(k == a), float(k == b)) for k in range(s.shape[1])]
        r = HyperDual.of(self.fn(v, y))
        full = lambda x: np.broadcast_to(np.asarray(x, np.float64), (len(s),))
        return full(r.b), full(r.d)

    def grad(self, s, y):
        return np.stack([self._second(s, y, k, k)[0] for k in range(s.shape[1])], axis=1)

    def diag(self, s, y):
        return np.stack([self._second(s, y, k, k)[1] for k in range(s.shape[1])], axis=1)

    def full(self, s, y):
        c = s.shape[1]
        h = np.zeros((len(s), c, c))
        for a in range(c):
            for b in range(a, c):
                h[:, a, b] = h[:, b, a] = self._second(s, y, a, b)[1]
        return h

    def predict(self, s):
        return self._predict(s)


class PairwiseLogistic(Loss):
    """Ranking within groups: the sum of log(1 + exp(s_low - s_high)) over pairs of different grades of one group.

    One output; y holds (grade, group) rows, and all rows of a group come together. A row's value is half that of its pairs,
    so rows add up to the sum over pairs. Pairs are formed in blocks of STEP rows, so memory grows with a group's rows, not
    with its pairs.
    """

    kind, STEP = "rank", 1024

    def _sums(self, s, y):
        s, grade, group = s[:, 0], y[:, 0], y[:, 1]
        loss, g, h = np.zeros(len(s)), np.zeros(len(s)), np.zeros(len(s))
        order = np.argsort(group, kind="stable")
        for i in np.split(order, np.flatnonzero(np.diff(group[order])) + 1):
            for k in range(0, len(i), self.STEP):
                a = i[k : k + self.STEP]
                d, sign = s[a][:, None] - s[i][None, :], np.sign(grade[a][:, None] - grade[i][None, :])
                p = sigmoid(-d * sign) * (sign != 0)  # how wrong each pair is
                loss[a] += 0.5 * (np.logaddexp(0, -d * sign) * (sign != 0)).sum(axis=1)
                g[a] -= (p * sign).sum(axis=1)
                h[a] += (p * (1 - p) * (sign != 0)).sum(axis=1)
        return loss, g, h

    def value(self, s, y):
        return self._sums(s, y)[0]

    def grad(self, s, y):
        return self._sums(s, y)[1][:, None]

    def diag(self, s, y):
        return self._sums(s, y)[2][:, None]

    def full(self, s, y):
        return self.diag(s, y)[:, :, None]

    def predict(self, s):
        return s

    def derivatives(self, s: np.ndarray, grade: np.ndarray, group: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        """(loss, gradient, diagonal curvature) of scores in one array."""
        loss, g, h = self._sums(np.asarray(s, float)[:, None], np.stack([grade, group], axis=1).astype(float))
        return float(loss.sum()), g, h


REGISTERED: dict[str, Loss] = {}


def register(name: str, loss: Loss) -> None:
    """Makes a user's loss known by name; in a cluster, from a module that executors import."""
    REGISTERED[name] = loss


def loss_of(name: str, outputs: int, encoding: str = "onehot", zero_sum: str | None = None, mu: float = 1.0) -> Loss:
    made = REGISTERED.get(name) or {
        "softmax": SoftmaxXent, "logistic": Logistic, "squared": SquaredError, "multilabel": MultiLabelLogistic, "pairwise": PairwiseLogistic,
        "multiexp": lambda: MultiExp(codewords(outputs, encoding)), "marginexp": lambda: MarginExp(codewords(outputs, encoding)),
    }[name]()
    return ZeroSum(made, mu) if zero_sum == "penalty" else made
