"""The arithmetic of a layer in NumPy: sums by node, feature and bin, and the best splits of summed cells.

The distributed engine runs it in its tasks; LocalRows runs all of it in one process, for tables of a checked size.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..config import BoostConfig
from ..functions.losses import Loss, loss_of
from ..functions.solve import Hessian, hessian_of
from .model import Model, Tree

GAIN_DIGITS = 9
#: Bytes of dense sums a task may hold (features beyond go to further passes), and elements handled at a time.
HELD, STEP = 256 << 20, 1 << 21


@dataclass
class Wip:
    """A tree being grown. direction: None for a vector tree, else the sums are those of g.u and u.H.u; commit: what
    a scalar weight becomes in the scores."""

    tree: Tree
    direction: np.ndarray | None = None
    commit: np.ndarray | None = None
    open: tuple[int, ...] = (1,)


@dataclass
class Split:
    tree: int
    node: int
    feature: int
    bin: int
    default_left: bool
    gain: float
    n: int
    nl: int
    nr: int
    w: list[float]
    wl: list[float]
    wr: list[float]


def loss_for(cfg: BoostConfig) -> Loss:
    return loss_of(cfg.loss, cfg.outputs, cfg.label_encoding, cfg.zero_sum, cfg.zero_sum_mu)


def hessian_for(cfg: BoostConfig, scalar: bool) -> Hessian:
    return hessian_of("diagonal", 1) if scalar else hessian_of(cfg.hessian, cfg.outputs, cfg.solver, cfg.hessian_scale, cfg.blocks, cfg.zero_sum)


def bins_of(model: Model) -> int:
    """Cells a feature: the missing ones, and one more than there are edges."""
    return max((len(e) for e in model.edges), default=0) + 2


def row_stats(cfg: BoostConfig, loss: Loss, wips: list[Wip], s: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, copies: np.ndarray | None = None) -> list[np.ndarray]:
    """For each tree, (1, gradients, curvatures) of every row, or those of its copies together."""
    hess, g = hessian_for(cfg, False), loss.grad(s, y)
    h = hess.rows(loss, s, y) if any(t.direction is None for t in wips) else None
    d, out = None, []
    for t in wips:
        if t.direction is None:
            stats = np.concatenate([g, h], axis=1)
        else:
            u = t.direction
            if np.count_nonzero(u) == 1:
                d = loss.diag(s, y) if d is None else d
                uhu = d @ (u * u)
            else:
                uhu = np.einsum("a,iab,b->i", u, loss.full(s, y), u)
            stats = np.stack([g @ u, cfg.hessian_scale * uhu], axis=1)
        own = np.concatenate([np.ones((len(s), 1)), stats if weight is None else stats * weight[:, None]], axis=1)
        out.append(own if copies is None else own * copies[:, None])
    return out


def add_up(out: np.ndarray, x: np.ndarray, slot: np.ndarray, stats: np.ndarray) -> None:
    """Adds rows to out [slots, features, bins, width]; slot: of each row, or -1."""
    slots, m, bins, width = out.shape
    rows = np.flatnonzero(slot >= 0)
    flat = out.reshape(-1, width)
    base = np.arange(m, dtype=np.int64) * bins
    for k in range(0, len(rows), max(1, STEP // max(1, m))):
        some = rows[k : k + max(1, STEP // max(1, m))]
        at = (x[some] + (slot[some] * (m * bins))[:, None] + base[None, :]).ravel()
        for c in range(width):
            flat[:, c] += np.bincount(at, np.repeat(stats[some, c], m), len(flat))


def places(wip: Wip, node: np.ndarray, summed: tuple[int, ...]) -> np.ndarray:
    """The position of each row's node among those summed, or -1."""
    of = np.full(2 ** (wip.tree.depth + 1), -1, np.int64)
    of[list(summed)] = np.arange(len(summed))
    return of[node]


def search(total: np.ndarray, cfg: BoostConfig, hess: Hessian, lam: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of cells [k, bins, 1 + c + width]: the best (gain, bin, default_left, left sums) of each. Ties: missing to the left
    first, then the least bin."""
    k, bins, _ = total.shape
    c = hess.c
    all_, none = total.sum(axis=1), total[:, 0]
    cum = np.cumsum(total[:, 1:], axis=1)
    some = none[:, 0] > 0
    left = np.concatenate([cum[:, :-1] + none[:, None], cum], axis=1)  # missing to the left; then to the right
    legal = np.ones((k, left.shape[1]), bool)
    legal[:, bins - 2 :] = some[:, None]
    n, nl = all_[:, None, 0], left[:, :, 0]
    legal &= (nl >= 1) & (n - nl >= 1)
    at = np.nonzero(legal)
    gains = np.full(legal.shape, -np.inf)
    if len(at[0]):
        parent = hess.gain(all_[:, 1 : 1 + c], all_[:, 1 + c :], all_[:, 0], lam)
        value = -parent[at[0]] - cfg.gamma
        for part in (left[at], all_[at[0]] - left[at]):
            value = value + hess.gain(part[:, 1 : 1 + c], part[:, 1 + c :], part[:, 0], lam)
            if cfg.min_child_weight > 0:
                d = hess.diagonal(part[:, 1 + c :], part[:, 0])
                weight = {"mean": d.mean(axis=1), "sum": d.sum(axis=1), "count": part[:, 0]}[cfg.mcw_mode]
                value = np.where(weight >= cfg.min_child_weight, value, -np.inf)
        gains[at] = np.round(value, GAIN_DIGITS)
    if not gains.shape[1]:
        return np.full(k, -np.inf), np.zeros(k, np.int64), np.ones(k, bool), all_
    best = gains.argmax(axis=1)
    rows = np.arange(k)
    default_left = best < bins - 2
    return gains[rows, best], np.where(default_left, best, best - (bins - 2)) + 1, default_left, left[rows, best]


def best_of(keys: np.ndarray, total: np.ndarray, cfg: BoostConfig, scalar: bool, layer_rows: float) -> list[Split]:
    """keys: (tree, node, feature) rows; total: their cells. The best split of each (tree, node): greatest gain, least feature,
    least bin. layer_rows: rows that the layer read, by which a per-instance L2 is multiplied."""
    hess = hessian_for(cfg, scalar)
    c, lam = hess.c, cfg.lam * (layer_rows if cfg.l2_mode == "per_instance" else 1)
    found = []
    size = max(1, STEP // max(1, total.shape[1] * total.shape[2] * (1 if hess.width <= 2 * c else c)))
    for k in range(0, len(keys), size):
        found.append(search(total[k : k + size], cfg, hess, lam))
    if not found:
        return []
    gain, bin_, default_left, left = map(np.concatenate, zip(*found))
    order = np.lexsort((keys[:, 2], -gain, keys[:, 1], keys[:, 0]))
    first = order[np.concatenate([[True], np.any(keys[order[1:], :2] != keys[order[:-1], :2], axis=1)])]
    all_ = total[first].sum(axis=1)
    weight = lambda v: hess.weight(v[:, 1 : 1 + c], v[:, 1 + c :], v[:, 0], lam)
    w, wl, wr = weight(all_), weight(left[first]), weight(all_ - left[first])
    out = []
    for i, k in enumerate(first):
        ok = np.isfinite(gain[k])
        nl = int(round(left[k, 0])) if ok else 0
        n = int(round(all_[i, 0]))
        out.append(Split(*map(int, keys[k]), int(bin_[k]), bool(default_left[k]), float(gain[k]), n, nl, n - nl if ok else 0, w[i].tolist(), wl[i].tolist() if ok else [], wr[i].tolist() if ok else []))
    return out


def pack_cells(v: np.ndarray) -> bytes:
    """Sums [bins, width] without the bins that no row fell in."""
    at = np.flatnonzero(v[:, 0])
    return at.astype("<u2").tobytes() + v[at].astype("<f8").tobytes()


def add_cells(out: np.ndarray, raw: bytes) -> None:
    """Adds what pack_cells gave to out [bins, width]."""
    width = out.shape[1]
    k = len(raw) // (2 + 8 * width)
    out[np.frombuffer(raw, "<u2", k)] += np.frombuffer(raw, "<f8", k * width, 2 * k).reshape(k, width)


class LocalRows:
    """A binned table in one process: what the engine asks of a distributed one, for tables of a checked size.

    Quotas are not drawn here; callers with rows_per_layer use the distributed rows. copies: how many equal rows each stands for.
    """

    def __init__(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, group: np.ndarray | None = None, copies: np.ndarray | None = None):
        self.x, self.y, self.weight, self.group, self.copies = x, y, weight, group, copies
        self._scores: tuple[Model, int, np.ndarray] | None = None
        self._stats: tuple[Model, int, list[Wip], list[np.ndarray]] | None = None

    def __len__(self) -> int:
        return len(self.x) if self.copies is None else int(self.copies.sum())

    def where(self, keep: np.ndarray) -> LocalRows:
        return LocalRows(self.x[keep], self.y[keep], *(v if v is None else v[keep] for v in (self.weight, self.group, self.copies)))

    def scores(self, model: Model) -> np.ndarray:
        """Of the committed trees; those added since the last call are added to what it gave."""
        if self._scores is None or self._scores[0] is not model:
            s, done = np.tile(model.base, (len(self.x), 1)), 0
        else:
            _, done, s = self._scores
        if done > len(model.trees):
            s, done = np.tile(model.base, (len(self.x), 1)), 0
        for t in model.trees[done:]:
            t.descend(self.x, s)
        self._scores = (model, len(model.trees), s)
        return s

    def targets(self) -> np.ndarray:
        return self.y if self.group is None else np.stack([self.y.astype(float), self.group.astype(float)], axis=1)

    def stats(self, model: Model, wips: list[Wip], s: np.ndarray, fresh: bool) -> list[np.ndarray]:
        """row_stats; where the scores stay the same down the trees, those of the layer above are kept."""
        had, self._stats = self._stats, None
        if not fresh and had is not None and had[0] is model and had[1] == len(model.trees) and len(had[2]) == len(wips) and all(a is b for a, b in zip(had[2], wips)):
            out = had[3]
        else:
            had = None
            out = row_stats(model.config, loss_for(model.config), wips, s, self.targets(), self.weight, self.copies)
        if not fresh:
            self._stats = (model, len(model.trees), list(wips), out)
        return out

    def splits(self, model: Model, wips: list[Wip], fresh: bool, features: int | None = None) -> list[Split]:
        cfg = model.config
        s = self.scores(model)
        if fresh:
            s = s.copy()
        spots = [t.tree.descend(self.x, s if fresh else None) for t in wips]
        stats = self.stats(model, wips, s, fresh)
        x = self.x if features is None else self.x[:, :features]
        bins, out = bins_of(model), []
        for k, (t, spot, st) in enumerate(zip(wips, spots, stats)):
            if not t.open:
                continue
            total = np.zeros((len(t.open), x.shape[1], bins, st.shape[1]))
            add_up(total, x, places(t, spot, t.open), st)
            keys = np.array([(k, j, f) for j in t.open for f in range(x.shape[1])])
            held = total[:, 0, :, 0].sum(axis=1) > 0  # nodes with rows
            keep = np.repeat(held, x.shape[1])
            out += best_of(keys[keep], total.reshape(-1, bins, st.shape[1])[keep], cfg, t.direction is not None, len(self))
        return out

    def loss(self, model: Model, by_class: bool = False):
        loss = loss_for(model.config)
        v = loss.value(self.scores(model), self.targets())
        if by_class:
            return {int(k): float(np.average(v[self.y == k], weights=None if self.copies is None else self.copies[self.y == k])) for k in np.unique(self.y)}
        return float(np.average(v, weights=self.copies)) if len(v) else 0.0
