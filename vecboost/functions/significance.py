"""Student's t for comparing methods, without a statistics library."""

from __future__ import annotations

import math


def _beta_fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function (modified Lentz)."""
    tiny = 1e-300
    c, d = 1.0, 1 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    out = d
    for m in range(1, 400):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + num * d
            c = 1 + num / c
            d, c = 1 / (d if abs(d) > tiny else tiny), c if abs(c) > tiny else tiny
            out *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return out


def incomplete_beta(a: float, b: float, x: float) -> float:
    if x <= 0 or x >= 1:
        return float(x >= 1)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    if x < (a + 1) / (a + b + 2):
        return front * _beta_fraction(a, b, x) / a
    return 1 - front * _beta_fraction(b, a, 1 - x) / b


def two_sided(t: float, df: float) -> float:
    """P(|T| >= |t|)."""
    return 1.0 if t == 0 else 0.0 if math.isinf(t) else incomplete_beta(df / 2, 0.5, df / (df + t * t))


def unpaired_t(m1, s1, n1, m2, s2, n2, pooled: bool = False) -> tuple[float, float, float]:
    """(t, degrees of freedom, two-sided p) from means, standard deviations and counts."""
    v1, v2 = s1 * s1 / n1, s2 * s2 / n2
    if pooled:
        df = n1 + n2 - 2
        se = math.sqrt(((n1 - 1) * s1 * s1 + (n2 - 1) * s2 * s2) / df * (1 / n1 + 1 / n2))
    else:
        se = math.sqrt(v1 + v2)
        df = (v1 + v2) ** 2 / (v1 * v1 / (n1 - 1) + v2 * v2 / (n2 - 1)) if se else n1 + n2 - 2
    t = 0.0 if m1 == m2 else math.copysign(math.inf, m1 - m2) if not se else (m1 - m2) / se
    return t, df, two_sided(t, df)


def paired_t(mean_difference, sd_difference, n) -> tuple[float, float, float]:
    t = 0.0 if not mean_difference else math.copysign(math.inf, mean_difference) if not sd_difference else mean_difference / (sd_difference / math.sqrt(n))
    return t, n - 1, two_sided(t, n - 1)


def best_set(rows: list[dict], metric: str = "accuracy", greater: bool = True, alpha: float = 0.05, without: tuple[str, ...] = ()) -> set[str]:
    """Methods not significantly different from the best mean. rows: method, <metric>, <metric>_sd, n_test."""
    rows = [r for r in rows if r[metric] is not None and r["method"] not in without]
    if not rows:
        return set()
    top = (max if greater else min)(rows, key=lambda r: r[metric])
    test = lambda r: unpaired_t(top[metric], top[f"{metric}_sd"], top["n_test"], r[metric], r[f"{metric}_sd"], r["n_test"])[2]
    return {r["method"] for r in rows if r is top or test(r) >= alpha}
