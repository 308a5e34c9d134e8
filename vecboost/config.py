"""Every parameter of a training run, checked in one place."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, replace


@dataclass(frozen=True)
class BoostConfig:
    outputs: int = 3
    loss: str = "softmax"  # softmax, logistic, squared, multilabel, multiexp, marginexp, pairwise, or a registered name
    label_encoding: str = "onehot"  # onehot, centered, simplex
    hessian: str = "diagonal"  # diagonal, full, identity, pair, block
    blocks: tuple[tuple[int, ...], ...] = ()
    hessian_scale: float = 1.0
    solver: str = "pivoted_qr"  # pivoted_qr, svd, normal, cholesky, closed
    schedule: str = "tree"  # tree, layer, per_class
    refresh: str = "tree"  # of per_class: after each tree, once a round, or after each layer of each tree
    root_contributes: bool = True
    n_trees: int = 10
    depth: int = 4
    eta: float = 0.3
    lam: float = 1.0
    l2_mode: str = "absolute"  # or per_instance: lam times the rows that the layer read
    gamma: float = 0.0
    pruning: str = "pre"  # pre, post
    min_child_weight: float = 0.0
    mcw_mode: str = "mean"  # mean, sum, count
    bins: int = 32
    rows_per_layer: int | tuple[int, ...] | None = None  # None: the whole training set
    zero_sum: str | None = None  # penalty, multiplier
    zero_sum_mu: float = 1.0
    base: str = "zero"  # or prior
    rescore: str = "carried"  # scores of committed trees kept on disk, or 'stateless': computed anew each pass
    patience: int | None = None
    max_full_classes: int = 64
    seed: int = 7

    def __post_init__(self):
        for name, allowed in {"hessian": "diagonal full identity pair block", "solver": "pivoted_qr svd normal cholesky closed", "schedule": "tree layer per_class", "refresh": "tree round layer", "l2_mode": "absolute per_instance", "pruning": "pre post", "mcw_mode": "mean sum count", "label_encoding": "onehot centered simplex", "base": "zero prior", "rescore": "carried stateless"}.items():
            if getattr(self, name) not in allowed.split():
                raise ValueError(f"{name}={getattr(self, name)!r}: one of {allowed}")
        if self.outputs < 1 or self.depth < 1 or not 1 <= self.bins <= 254 or self.lam < 0 or self.gamma < 0:
            raise ValueError("outputs, depth >= 1; 1 <= bins <= 254; lam, gamma >= 0")
        if self.hessian == "full" and self.outputs > self.max_full_classes:
            raise ValueError(f"a full Hessian of {self.outputs} outputs costs {self.outputs**2} sums a cell; raise max_full_classes to insist")

    @property
    def layered(self) -> bool:
        """Whether every layer is a step of its own, with gradients taken anew."""
        return self.schedule == "layer" or self.schedule == "per_class" and self.refresh == "layer"

    def but(self, **changes) -> BoostConfig:
        return replace(self, **changes)

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> BoostConfig:
        d = json.loads(text)
        d["blocks"] = tuple(tuple(b) for b in d["blocks"])
        if isinstance(d["rows_per_layer"], list):
            d["rows_per_layer"] = tuple(d["rows_per_layer"])
        return BoostConfig(**d)

    def quota(self, layer: int) -> int | None:
        """Rows that layer (0 the root's) asks for."""
        q = self.rows_per_layer
        return q if q is None or isinstance(q, int) else q[min(layer, len(q) - 1)]

    def leaf_bytes(self) -> int:
        """Of the whole ensemble's leaf vectors: a guide to how many outputs are too many."""
        return self.n_trees * 2**self.depth * self.outputs * 8
