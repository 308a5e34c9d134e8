"""The steps of split search as Catalyst expressions: for few outputs, all inside code generation.

Statistics are plain columns (n, g0.., h0..). Curvature columns are the diagonal, then (packed) the pairs (a, b), a < b.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def softmax_columns(scores: list[Column]) -> list[Column]:
    top = F.greatest(*scores) if len(scores) > 1 else scores[0]
    e = [F.exp(s - top) for s in scores]
    total = sum(e[1:], e[0])
    return [x / total for x in e]


def softmax_stats(scores: list[Column], y: Column, packed: bool = False) -> tuple[list[Column], list[Column]]:
    p = softmax_columns(scores)
    g = [x - (y == k).cast("double") for k, x in enumerate(p)]
    h = [x * (1 - x) for x in p]
    if packed:
        h += [-p[a] * p[b] for a in range(len(p)) for b in range(a + 1, len(p))]
    return g, h


def named(g: list[Column], h: list[Column]) -> list[Column]:
    return [x.alias(f"g{k}") for k, x in enumerate(g)] + [x.alias(f"h{k}") for k, x in enumerate(h)]


def histogram(rows: DataFrame, bins: list[str], stats: list[str], keys: tuple[str, ...] = ("node",), decimal: bool = False) -> DataFrame:
    """(keys, feature, bin, n, stats): one row a non-empty cell; partial sums before the exchange.

    decimal: sums of decimal(38,12) values, the same whatever the order of rows.
    """
    one = [F.struct(F.lit(i).alias("feature"), F.col(b).alias("bin")) for i, b in enumerate(bins)]
    value = (lambda c: F.sum(F.col(c).cast("decimal(28,12)"))) if decimal else F.sum
    e = rows.select(*keys, *stats, F.explode(F.array(*one)).alias("c")).select(*keys, *stats, "c.feature", "c.bin")
    return e.groupBy(*keys, "feature", "bin").agg(F.count("*").alias("n"), *[value(s).alias(s) for s in stats])


def prefix(hist: DataFrame, stats: list[str], keys: tuple[str, ...] = ("node",)) -> DataFrame:
    """Adds l_* (sums up to the bin) and t_* (totals) for n and stats; one exchange on (keys, feature)."""
    w = W.partitionBy(*keys, "feature").orderBy("bin").rowsBetween(W.unboundedPreceding, W.currentRow)
    all_ = W.partitionBy(*keys, "feature")
    return hist.select(*keys, "feature", "bin", *[F.sum(s).over(w).alias(f"l_{s}") for s in ("n", *stats)], *[F.sum(s).over(all_).alias(f"t_{s}") for s in ("n", *stats)])


def weights_of(g: list[Column], h: list[Column], n: Column, lam: float, kind: str = "diagonal", zero_sum: bool = False) -> list[Column]:
    """Leaf vectors as columns; kinds diagonal, identity, and full up to three outputs."""
    c = len(g)
    if kind in ("diagonal", "identity"):
        a = [(h[k] if kind == "diagonal" else n) + lam for k in range(c)]
        nu = -sum((x / y for x, y in zip(g[1:], a[1:])), g[0] / a[0]) / sum((1 / y for y in a[1:]), 1 / a[0]) if zero_sum else F.lit(0.0)
        return [-(g[k] + nu) / a[k] for k in range(c)]
    pairs = [(a, b) for a in range(c) for b in range(a + 1, c)]
    m = {(k, k): h[k] + lam for k in range(c)}
    for (a, b), x in zip(pairs, h[c:]):
        m[a, b] = m[b, a] = x
    if c == 1:
        return [-g[0] / m[0, 0]]
    if c == 2:
        det = m[0, 0] * m[1, 1] - m[0, 1] * m[0, 1]
        return [-(m[1, 1] * g[0] - m[0, 1] * g[1]) / det, -(m[0, 0] * g[1] - m[0, 1] * g[0]) / det]
    adj = {(i, j): m[(i + 1) % 3, (j + 1) % 3] * m[(i + 2) % 3, (j + 2) % 3] - m[(i + 1) % 3, (j + 2) % 3] * m[(i + 2) % 3, (j + 1) % 3] for i in range(3) for j in range(3)}
    det = sum((m[0, j] * adj[0, j] for j in (1, 2)), m[0, 0] * adj[0, 0])
    return [-sum((adj[i, k] * g[i] for i in (1, 2)), adj[0, k] * g[0]) / det for k in range(3)]


def gain(g: list[Column], h: list[Column], n: Column, lam: float, kind: str = "diagonal", zero_sum: bool = False) -> Column:
    w = weights_of(g, h, n, lam, kind, zero_sum)
    return -0.5 * sum((a * b for a, b in zip(g[1:], w[1:])), g[0] * w[0])


def candidates(pre: DataFrame, c: int, n_h: int, lam: float, kind: str = "diagonal", gamma: float = 0.0, keys: tuple[str, ...] = ("node",), weights: bool = False, zero_sum: bool = False, whole: bool = False) -> DataFrame:
    """(keys, feature, bin, nl, nr, gain) of every legal split; right = total - left.

    weights: also the vectors w, wl, wr of the node and of its children. whole: also a row without a split (gain null) for
    each node, that all rows lie left of.
    """
    col = lambda s, k, n: [F.col(f"{s}_{k}{i}") for i in range(n)]
    gl, hl, gt, ht = col("l", "g", c), col("l", "h", n_h), col("t", "g", c), col("t", "h", n_h)
    gr, hr = [t - x for t, x in zip(gt, gl)], [t - x for t, x in zip(ht, hl)]
    nl, nt = F.col("l_n"), F.col("t_n")
    sides = [(gt, ht, nt), (gl, hl, nl), (gr, hr, nt - nl)]
    value = gain(*sides[1], lam, kind, zero_sum) + gain(*sides[2], lam, kind, zero_sum) - gain(*sides[0], lam, kind, zero_sum) - gamma
    value = F.when(nl < nt, F.round(value, 9))
    made = [F.array(*weights_of(*side, lam, kind, zero_sum)).alias(n) if n == "w" else F.when(nl < nt, F.array(*weights_of(*side, lam, kind, zero_sum))).alias(n) for n, side in zip(("w", "wl", "wr"), sides)] if weights else []
    rows = pre if whole else pre.where("l_n < t_n")
    return rows.select(*keys, "feature", "bin", nl.alias("nl"), (nt - nl).alias("nr"), value.alias("gain"), *made)


def best(cands: DataFrame, keys: tuple[str, ...] = ("node",), top: int = 1) -> DataFrame:
    """The `top` splits of each node: gain, then least feature, then least bin."""
    w = W.partitionBy(*keys).orderBy(F.desc("gain"), "feature", "bin")
    return cands.withColumn("place", F.row_number().over(w)).where(F.col("place") <= top)
