"""Configurations under which other multiclass boosters come out of the same engine."""

from __future__ import annotations

from ..config import BoostConfig


def diag(outputs: int, **k) -> BoostConfig:
    return BoostConfig(outputs=outputs, **k)


def full(outputs: int, **k) -> BoostConfig:
    return BoostConfig(outputs=outputs, hessian="full", **k)


def diag_lbl(outputs: int, **k) -> BoostConfig:
    """Diagonal Hessian, layer by layer: the first choice for small ensembles."""
    return BoostConfig(outputs=outputs, schedule="layer", **k)


def full_lbl(outputs: int, **k) -> BoostConfig:
    return BoostConfig(outputs=outputs, hessian="full", schedule="layer", **k)


def per_class(outputs: int, **k) -> BoostConfig:
    return BoostConfig(**{"outputs": outputs, "schedule": "per_class", "refresh": "tree", **k})


def per_class_lbl(outputs: int, **k) -> BoostConfig:
    """A scalar tree a class, its layers steps of their own."""
    return BoostConfig(**{"outputs": outputs, "schedule": "per_class", "refresh": "layer", **k})


def logitboost_compact(outputs: int, **k) -> BoostConfig:
    """Logistic boosting with one tree for all classes."""
    return BoostConfig(outputs=outputs, loss="softmax", hessian="diagonal", **k)


def samme_like(outputs: int, **k) -> BoostConfig:
    """Multiclass exponential loss, zero-sum scores, no second-order information."""
    return BoostConfig(outputs=outputs, loss="multiexp", label_encoding="centered", hessian="identity", zero_sum="multiplier", **k)


def gamble_like(outputs: int, **k) -> BoostConfig:
    """Multiclass exponential loss on centred codes, unregularised; the summed Hessian is singular, so the least-norm solution is taken."""
    return BoostConfig(outputs=outputs, loss="multiexp", label_encoding="centered", hessian="full", solver="svd", **{"lam": 0.0, "gamma": 0.0, **k})


def aoso_like(outputs: int, **k) -> BoostConfig:
    """Logistic loss, each node moving along its best pair of classes."""
    return BoostConfig(outputs=outputs, loss="softmax", hessian="pair", **k)


def gd_mc_like(outputs: int, **k) -> BoostConfig:
    """Exponential margins over simplex codewords, first order."""
    return BoostConfig(outputs=outputs, loss="marginexp", label_encoding="simplex", hessian="identity", **k)


PRESETS = {f.__name__: f for f in (diag, full, diag_lbl, full_lbl, per_class, per_class_lbl, logitboost_compact, samme_like, gamble_like, aoso_like, gd_mc_like)}
