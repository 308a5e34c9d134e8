"""Leaf systems (H + lam I) w = -G, batched: full matrices by several solvers, and structured Hessians.

A Hessian kind says which sums a cell holds, and gives weights and gains from them.
"""

from __future__ import annotations

import numpy as np


def pivoted_qr(a: np.ndarray, b: np.ndarray, tol: float = 1e-12) -> np.ndarray:
    """Householder QR with column pivoting over a batch; columns of negligible size get zero."""
    a, b = a.copy(), b.copy()
    n, c = b.shape
    perm = np.tile(np.arange(c), (n, 1))
    rows = np.arange(n)
    top = np.sqrt((a**2).sum(axis=1)).max(axis=1)
    rank = np.zeros(n, int)
    for k in range(c):
        j = k + (a[:, k:, k:] ** 2).sum(axis=1).argmax(axis=1)
        a[rows, :, k], a[rows, :, j] = a[rows, :, j].copy(), a[rows, :, k].copy()
        perm[rows, k], perm[rows, j] = perm[rows, j].copy(), perm[rows, k].copy()
        x = a[:, k:, k]
        norm = np.sqrt((x**2).sum(axis=1))
        live = norm > tol * np.maximum(top, 1e-300)
        rank += live
        v = x.copy()
        v[:, 0] += np.where(x[:, 0] >= 0, norm, -norm)
        size = (v**2).sum(axis=1)
        scale = np.where(live & (size > 0), 2 / np.where(size > 0, size, 1), 0)
        a[:, k:, k:] -= (scale[:, None] * v)[:, :, None] * np.einsum("ni,nij->nj", v, a[:, k:, k:])[:, None, :]
        b[:, k:] -= (scale[:, None] * v) * np.einsum("ni,ni->n", v, b[:, k:])[:, None]
    x = np.zeros_like(b)
    for k in range(c - 1, -1, -1):
        live = k < rank
        r = b[:, k] - np.einsum("nj,nj->n", a[:, k, k + 1 :], x[:, k + 1 :])
        x[:, k] = np.where(live, r / np.where(live, a[:, k, k], 1), 0)
    out = np.zeros_like(x)
    np.put_along_axis(out, perm, x, axis=1)
    return out


def svd(a, b):
    u, s, vt = np.linalg.svd(a)
    keep = s > 1e-12 * np.maximum(s[:, :1], 1e-300)
    y = np.einsum("nji,nj->ni", u, b) * np.where(keep, 1 / np.where(keep, s, 1), 0)
    return np.einsum("nji,nj->ni", vt, y)


def normal(a, b):
    at = a.transpose(0, 2, 1)
    return np.linalg.solve(at @ a, (at @ b[:, :, None]))[:, :, 0]


def cholesky(a, b):
    """Forward and back substitution a column at a time, over the whole batch; fails where a matrix isn't positive definite."""
    low, y = np.linalg.cholesky(a), b.astype(float)
    c = b.shape[1]
    for k in range(c):
        y[:, k] = (y[:, k] - np.einsum("nj,nj->n", low[:, k, :k], y[:, :k])) / low[:, k, k]
    for k in reversed(range(c)):
        y[:, k] = (y[:, k] - np.einsum("nj,nj->n", low[:, k + 1 :, k], y[:, k + 1 :])) / low[:, k, k]
    return y


def closed(a, b):
    """By adjugates, up to three outputs."""
    c = b.shape[1]
    if c == 1:
        return b / a[:, 0]
    if c == 2:
        det = a[:, 0, 0] * a[:, 1, 1] - a[:, 0, 1] * a[:, 1, 0]
        return np.stack([a[:, 1, 1] * b[:, 0] - a[:, 0, 1] * b[:, 1], a[:, 0, 0] * b[:, 1] - a[:, 1, 0] * b[:, 0]], 1) / det[:, None]
    if c > 3:
        raise ValueError("closed forms go up to three outputs")
    cols = [np.cross(a[:, 1], a[:, 2]), np.cross(a[:, 2], a[:, 0]), np.cross(a[:, 0], a[:, 1])]
    det = (a[:, 0] * cols[0]).sum(axis=1)
    return sum(cols[k] * b[:, k : k + 1] for k in range(3)) / det[:, None]


SOLVERS = {"pivoted_qr": pivoted_qr, "svd": svd, "normal": normal, "cholesky": cholesky, "closed": closed}


def check_spd(h: np.ndarray, lam: float) -> np.ndarray:
    """Whether each symmetric matrix of the batch plus lam I is positive definite."""
    h = np.asarray(h)
    even = np.abs(h - h.transpose(0, 2, 1)).max(axis=(1, 2)) <= 1e-9 * np.maximum(1, np.abs(h).max(axis=(1, 2)))
    return even & (np.linalg.eigvalsh((h + h.transpose(0, 2, 1)) / 2)[:, 0] + lam > 0)


class Hessian:
    """width: curvature sums a cell has; rows: those of a batch; weight, gain: of summed cells (n x ...)."""

    def __init__(self, c: int, solver: str = "pivoted_qr", scale: float = 1.0, blocks=(), multiplier: bool = False):
        self.c, self.solver, self.scale, self.blocks, self.multiplier = c, solver, scale, blocks, multiplier
        self.up = np.triu_indices(c)

    def weight(self, g, h, n, lam):
        raise NotImplementedError

    def gain(self, g, h, n, lam):
        """Decrease of the quadratic model at its own optimum: -(g.w + w.(H + lam)w / 2)."""
        return -0.5 * (g * self.weight(g, h, n, lam)).sum(axis=1)

    def diagonal(self, h, n):
        return h


class DiagonalH(Hessian):
    def __init__(self, c, **k):
        super().__init__(c, **k)
        self.width = c

    def rows(self, loss, s, y):
        return self.scale * loss.diag(s, y)

    def weight(self, g, h, n, lam):
        a = h + np.asarray(lam).reshape(-1, 1)
        a = np.where(a > 0, a, np.inf)
        if self.multiplier:
            nu = -(g / a).sum(axis=1) / (1 / a).sum(axis=1)
            return -(g + nu[:, None]) / a
        return -g / a


class IdentityH(DiagonalH):
    def __init__(self, c, **k):
        super().__init__(c, **k)
        self.width = 0

    def rows(self, loss, s, y):
        return np.zeros((len(s), 0))

    def weight(self, g, h, n, lam):
        return super().weight(g, np.repeat(np.asarray(n, float)[:, None], self.c, axis=1), n, lam)

    def diagonal(self, h, n):
        return np.repeat(np.asarray(n, float)[:, None], self.c, axis=1)


class FullH(Hessian):
    def __init__(self, c, **k):
        super().__init__(c, **k)
        self.width = c * (c + 1) // 2

    def rows(self, loss, s, y):
        return self.scale * loss.full(s, y)[:, self.up[0], self.up[1]]

    def matrix(self, h):
        m = np.zeros((len(h), self.c, self.c))
        m[:, self.up[0], self.up[1]] = h
        m[:, self.up[1], self.up[0]] = h
        return m

    def _solve(self, m, b):
        """By the solver chosen; systems that aren't positive definite are no case for Cholesky and go to the pivoted QR."""
        try:
            return SOLVERS[self.solver](m, b)
        except np.linalg.LinAlgError:
            if self.solver != "cholesky":
                raise
        fit, out = check_spd(m, 0.0), pivoted_qr(m, b)
        out[fit] = cholesky(m[fit], b[fit])
        return out

    def weight(self, g, h, n, lam):
        m = self.matrix(h) + np.asarray(lam).reshape(-1, 1, 1) * np.eye(self.c)
        w = self._solve(m, -g)
        if self.multiplier:
            one = self._solve(m, np.ones_like(g))
            w = w - one * (w.sum(axis=1) / one.sum(axis=1))[:, None]
        return w

    def diagonal(self, h, n):
        return h[:, self.up[0] == self.up[1]]


class PairH(FullH):
    """Moves along e_a - e_b for the pair of outputs that gains most."""

    def weight(self, g, h, n, lam):
        m, lam = self.matrix(h), np.broadcast_to(np.asarray(lam, float), (len(g),))
        d = np.einsum("njj->nj", m)
        a, b = np.triu_indices(self.c, 1)
        den = d[:, a] + d[:, b] - 2 * m[:, a, b] + 2 * lam[:, None]
        num = g[:, a] - g[:, b]
        best = np.where(den > 0, num**2 / np.where(den > 0, den, 1), 0).argmax(axis=1)
        rows, w = np.arange(len(g)), np.zeros_like(g)
        den, num = den[rows, best], num[rows, best]
        step = np.where(den > 0, -num / np.where(den > 0, den, 1), 0)
        w[rows, a[best]], w[rows, b[best]] = step, -step
        return w


class BlockH(FullH):
    """Solves each declared block of outputs on its own; outputs in no block are blocks of one."""

    def weight(self, g, h, n, lam):
        m, w = self.matrix(h), np.zeros_like(g)
        lam = np.broadcast_to(np.asarray(lam, float), (len(g),))
        named = {k for b in self.blocks for k in b}
        for b in [list(b) for b in self.blocks] + [[k] for k in range(self.c) if k not in named]:
            w[:, b] = self._solve(m[:, b][:, :, b] + lam[:, None, None] * np.eye(len(b)), -g[:, b])
        return w


KINDS = {"diagonal": DiagonalH, "identity": IdentityH, "full": FullH, "pair": PairH, "block": BlockH}


def hessian_of(kind: str, c: int, solver: str = "pivoted_qr", scale: float = 1.0, blocks=(), zero_sum: str | None = None) -> Hessian:
    return KINDS[kind](c, solver=solver, scale=scale, blocks=blocks, multiplier=zero_sum == "multiplier")
