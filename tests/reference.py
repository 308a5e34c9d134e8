"""Exact greedy boosting in plain NumPy, written apart from the engine."""

import numpy as np


def grad_hess(s, y):
    e = np.exp(s - s.max(1, keepdims=True))
    p = e / e.sum(1, keepdims=True)
    g = p - np.eye(s.shape[1])[y]
    h = np.einsum("ij,jk->ijk", p, np.eye(s.shape[1])) - np.einsum("ij,ik->ijk", p, p)
    return g, h


def solve(G, H, lam, full):
    return -np.linalg.solve(H + lam * np.eye(len(G)), G) if full else -G / (np.diag(H) + lam)


def gain(G, H, lam, full):
    return -0.5 * G @ solve(G, H, lam, full)


def boost(x, y, c, trees, depth, eta=0.3, lam=1.0, full=False, layered=False, root=True):
    s, out = np.zeros((len(x), c)), []
    for t in range(trees):
        node = np.ones(len(x), int)
        g, h = grad_hess(s, y)
        if layered and root:
            s = s + eta * solve(g.sum(0), h.sum(0), lam, full)
        for d in range(depth):
            if layered:
                g, h = grad_hess(s, y)
            new, delta = node.copy(), {}
            for j in range(2**d, 2 ** (d + 1)):
                rows = node == j
                if not rows.any():
                    continue
                best = (0, None)
                for f in range(x.shape[1]):
                    for b in np.unique(x[rows, f])[:-1]:
                        left, right = rows & (x[:, f] <= b), rows & (x[:, f] > b)
                        v = round(sum(gain(g[m].sum(0), h[m].sum(0), lam, full) for m in (left, right)) - gain(g[rows].sum(0), h[rows].sum(0), lam, full), 9)
                        if v > best[0]:
                            best = (v, (f, int(b), left, right))
                if best[1]:
                    f, b, left, right = best[1]
                    out.append((t, j, f, b, best[0]))
                    new[left], new[right] = 2 * j, 2 * j + 1
                    if layered:
                        for m in (left, right):
                            delta[int(new[m][0])] = (m, eta * solve(g[m].sum(0), h[m].sum(0), lam, full))
            for m, w in delta.values():
                s[m] += w
            node = new
        if not layered:
            s = s.copy()
            for j in np.unique(node):
                m = node == j
                s[m] += eta * solve(g[m].sum(0), h[m].sum(0), lam, full)
    return out, s
