"""Whole small boosters: the engine over fixed bins, and the same as unrolled SQL.

Each query gives a row a split (tree, node, feature, bin, n, gain) with the test accuracy or loss beside it. The SQL is
generated round by round from the formulas below, which share nothing with the engine's code.
"""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..config import BoostConfig
from ..operators import metrics
from ..operators.binning import bin_expr, binned
from ..operators.native import softmax_columns
from ..plans import presets
from ..plans.boost import fit, training_loss
from ..plans.jvm import JvmRows
from ..plans.model import score, score_expr
from ..plans.workloads import T3_EDGES, T3_FEATURES, slice3
from . import query

#: Test: the held-out orders. Label kinds of the small workload, as columns and as SQL.
Z_SQL = "l_quantity/50 + l_extendedprice/105000 + 5*l_discount + CASE WHEN month(l_shipdate) <= 6 THEN 12.5*l_tax ELSE 1 - 12.5*l_tax END"
Y_SQL = f"CASE WHEN {Z_SQL} > 2.4 THEN 2 WHEN {Z_SQL} > 1.6 THEN 1 ELSE 0 END"


def fixed_rows(spark, sf_dir, kind: str = "class"):
    d = slice3(spark, sf_dir)
    if kind == "binary":
        d = d.withColumn("y", (F.col("y") > 0).cast("int"))
    elif kind == "multi":
        d = d.withColumn("y", F.array((F.col("y") > 0).cast("double"), (F.col("l_tax") > 0.04).cast("double")))
    elif kind == "real":
        net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
        d = d.withColumn("y", F.array(net / 1000, net * (1 + F.col("l_tax")) / 1000))
    return binned(d, T3_FEATURES, T3_EDGES, ["test", "y"]).persist()


def told(spark, sf_dir, cfg: BoostConfig, how: str | None = None, kind: str = "class", **k):
    base = fixed_rows(spark, sf_dir, kind)
    train, test = base.where("not test").drop("test"), base.where("test").drop("test")
    model = fit(train, cfg, T3_EDGES, how, **k)
    loss = round(training_loss(test, model), 4)
    hit = round(score(test, model, ["y"]).agg(F.avg((F.col("prediction") == F.col("y")).cast("double"))).first()[0], 4) if kind in ("class", "binary") else None
    rows = [(t, j, int(x.feature[j]), int(x.bin[j]), int(x.n[j]), round(float(x.gain[j]), 4), hit, loss) for t, x in enumerate(model.trees) for j in x.nodes() if x.feature[j] >= 0]
    base.unpersist()
    return spark.createDataFrame(rows, "tree int, node int, feature int, bin int, n long, gain double, accuracy double, test_loss double")


class Sql:
    """Formulas of one booster: derivatives of a row, gain and weights of sums, loss."""

    def __init__(self, c: int, loss: str = "softmax", hessian: str = "diagonal", lam: float = 1.0, scale: float = 1.0, zero_sum: bool = False):
        self.c, self.loss, self.hessian, self.lam, self.scale, self.zero_sum = c, loss, hessian, lam, scale, zero_sum
        self.pairs = [(a, b) for a in range(c) for b in range(a + 1, c)]

    def code(self, y: int, k: int) -> float:
        if self.loss == "multiexp":
            return 1.0 if y == k else -1 / (self.c - 1)
        return ((1.0 if y == k else 0.0) - 1 / self.c) / math.sqrt(1 - 1 / self.c)

    def of_y(self, f) -> str:
        return "CASE y " + " ".join(f"WHEN {y} THEN {f(y)}" for y in range(self.c)) + " END"

    def row(self) -> tuple[list[str], list[str], list[str], str]:
        """(helpers, g, packed h, loss) over s0.., y or y0..; helpers are named e0.. or ex."""
        c, s = self.c, [f"s{k}" for k in range(self.c)]
        if self.loss == "softmax":
            m = f"greatest({', '.join(s)})"
            e = [f"exp({x}-{m})" for x in s]
            p = [f"e{k}/({'+'.join(f'e{j}' for j in range(c))})" for k in range(c)]
            g = [f"{p[k]} - (y={k})::INT" for k in range(c)]
            h = [f"{p[k]}*(1-{p[k]})" for k in range(c)] if self.hessian == "diagonal" else [f"{p[k]}*(1-{p[k]})" for k in range(c)] + [f"-({p[a]})*({p[b]})" for a, b in self.pairs]
            return e, g, h, f"-ln(greatest({self.of_y(lambda y: p[y])}, 1e-15))"
        if self.loss == "squared":
            return [], [f"s{k}-y{k}" for k in range(c)], ["1.0"] * c, "+".join(f"0.5*(s{k}-y{k})*(s{k}-y{k})" for k in range(c))
        if self.loss == "multilabel":
            e = [f"1/(1+exp(-s{k}))" for k in range(c)]
            y = ["y"] if c == 1 else [f"y{k}" for k in range(c)]
            return e, [f"e{k}-{y[k]}" for k in range(c)], [f"e{k}*(1-e{k})" for k in range(c)], "+".join(f"(-({y[k]}*ln(e{k})+(1-{y[k]})*ln(1-e{k})))" for k in range(c))
        if self.loss == "multiexp":
            u = [self.of_y(lambda y, k=k: repr(self.code(y, k) / c)) for k in range(c)]
            e = ["exp(-(" + "+".join(f"({u[k]})*s{k}" for k in range(c)) + "))"]
            return e, [f"-({u[k]})*e0" for k in range(c)], [f"({u[k]})*({u[k]})*e0" for k in range(c)] + [f"({u[a]})*({u[b]})*e0" for a, b in self.pairs], "e0"
        # margins over simplex codewords: one helper for each other class
        d = lambda y, k, j: (self.code(y, j) - self.code(k, j)) / 2
        e = [self.of_y(lambda y, k=k: "0.0" if y == k else "exp(-(" + "+".join(f"({d(y, k, j)!r})*s{j}" for j in range(c)) + "))") for k in range(c)]
        g = ["-(" + "+".join(f"e{k}*({self.of_y(lambda y, k=k, j=j: repr(d(y, k, j)))})" for k in range(c)) + ")" for j in range(c)]
        return e, g, ["0.0"] * c, "+".join(f"e{k}" for k in range(c))

    def n_h(self) -> int:
        return len(self.row()[2])

    def weight(self, g: list[str], h: list[str], n: str) -> list[str]:
        c, lam = self.c, self.lam
        if self.hessian in ("diagonal", "identity"):
            a = [f"({self.scale}*{h[k]}+{lam})" if self.hessian == "diagonal" else f"({n}+{lam})" for k in range(c)]
            if self.zero_sum:
                nu = f"(-({'+'.join(f'{g[k]}/{a[k]}' for k in range(c))})/({'+'.join(f'1/{a[k]}' for k in range(c))}))"
                return [f"(-({g[k]}+{nu})/{a[k]})" for k in range(c)]
            return [f"(-({g[k]})/{a[k]})" for k in range(c)]
        null = 1 if self.hessian == "least" else 0  # along (1, 1, 1) the sums are singular and g has no part: adding ones changes no solution
        m = {(k, k): f"({h[k]}+{lam + null})" for k in range(c)}
        for (a, b), x in zip(self.pairs, h[c:]):
            m[a, b] = m[b, a] = f"({x}+{null})"
        if self.hessian == "pair":
            num = [f"({g[a]}-{g[b]})" for a, b in self.pairs]
            den = [f"({m[a, a]}+{m[b, b]}-2*{m[a, b]})" for a, b in self.pairs]
            q = [f"({x}*{x}/{y})" for x, y in zip(num, den)]
            top = f"greatest({', '.join(q)})"
            first = lambda v: "CASE " + " ".join(f"WHEN {q[i]}={top} THEN {v(i)}" for i in range(len(q))) + " END"
            sign = lambda i, k: -1 if self.pairs[i][0] == k else 1 if self.pairs[i][1] == k else 0
            return [f"({first(lambda i, k=k: f'{sign(i, k)}*{num[i]}/{den[i]}' if sign(i, k) else '0.0')})" for k in range(c)]
        minor = lambda i, j: (lambda r, s: f"({m[r[0], s[0]]}*{m[r[1], s[1]]}-{m[r[0], s[1]]}*{m[r[1], s[0]]})")([x for x in range(3) if x != i], [x for x in range(3) if x != j])
        det = "(" + "+".join(f"({'' if j % 2 == 0 else '-'}{m[0, j]}*{minor(0, j)})" for j in range(3)) + ")"
        w = ["(-(" + "+".join(f"({'' if (i + k) % 2 == 0 else '-'}{minor(i, k)})*({g[i]})" for i in range(3)) + f")/{det})" for k in range(3)]
        if self.hessian != "least":
            return w
        # rows of one class leave a single direction, along which the least-norm step goes
        gg, trace = "(" + "+".join(f"({x})*({x})" for x in g) + ")", "(" + "+".join(f"({x})" for x in h[:c]) + ")"
        ghg = "(" + "+".join(f"({h[k]})*({g[k]})*({g[k]})" for k in range(c)) + "+" + "+".join(f"2*({x})*({g[a]})*({g[b]})" for (a, b), x in zip(self.pairs, h[c:])) + ")"
        return [f"(CASE WHEN {det} > 1e-9*{trace}*{trace} THEN {w[k]} WHEN {ghg} > 0 THEN -({g[k]})*{gg}/{ghg} ELSE 0 END)" for k in range(3)]

    def gain(self, g, h, n) -> str:
        w = self.weight(g, h, n)
        return "(-0.5*(" + "+".join(f"({g[k]})*{w[k]}" for k in range(self.c)) + "))"


def base_sql(kind: str) -> str:
    bins = ", ".join("CASE " + " ".join(f"WHEN {x} <= {e} THEN {i + 1}" for i, e in enumerate(cuts)) + f" ELSE {len(cuts) + 1} END AS b{f}" for f, (x, cuts) in enumerate(zip(T3_FEATURES, T3_EDGES)))
    if kind.isdigit():  # rows of two classes, the second against the first
        return f"SELECT * REPLACE ((y = {kind[1]})::INT AS y) FROM ({base_sql('class')}) WHERE y IN ({kind[0]}, {kind[1]})"
    y = {"class": f"{Y_SQL} AS y", "binary": f"({Z_SQL} > 1.6)::INT AS y", "multi": f"({Z_SQL} > 1.6)::INT AS y0, (l_tax > 0.04)::INT AS y1", "real": "l_extendedprice*(1-l_discount)/1000 AS y0, l_extendedprice*(1-l_discount)*(1+l_tax)/1000 AS y1"}[kind]
    return f"SELECT l_orderkey % 5 = 0 AS test, {bins}, {y} FROM lineitem"


def booster_sql(f: Sql, trees: int, depth: int, eta: float, kind: str = "class", layered: bool = False, root: bool = True, direction: list[tuple[list[float], list[float]]] | None = None, snapshot: int = 1, min_child: float = 0.0, measured: bool | None = True) -> str:
    """measured: with the splits, the test measures (None: those alone). direction: of each tree (u, v): scalar sums of g.u and u.H.u, leaf vectors w*v. snapshot: trees that share a gradient."""
    c, y = f.c, ", ".join({"class": ["y"], "binary": ["y"], "01": ["y"], "02": ["y"], "12": ["y"]}.get(kind, [f"y{k}" for k in range(f.c)]))
    keep = f"test, b0, b1, b2, b3, {y}"
    s = ", ".join(f"s{k}" for k in range(c))
    ctes = [f"z0 AS MATERIALIZED (SELECT {keep.replace('test', 'test', 1)}, {', '.join(f'0.0::DOUBLE AS s{k}, 0.0::DOUBLE AS r{k}' for k in range(c))}, 1 AS node FROM ({base_sql(kind)}))"]
    at, done = "z0", []
    helpers, g, h, loss = f.row()
    scalar = direction is not None
    one = Sql(1, f.loss, "diagonal", f.lam, f.scale) if scalar else f
    width = 1 if scalar else c
    n_h = 1 if scalar else len(h)
    G, H = [f"g{k}" for k in range(width)], [f"h{k}" for k in range(n_h)]

    def grads(name: str, source: str, t: int, where: str) -> str:
        from_ = f"(SELECT {keep}, node, {', '.join(f'{"r" if snapshot > 1 else "s"}{k} AS s{k}' for k in range(c))} FROM {source})"
        inner = f"SELECT *, {', '.join(f'{x} AS e{k}' for k, x in enumerate(helpers))} FROM {from_}" if helpers else f"SELECT * FROM {from_}"
        if scalar:
            u = direction[t][0]
            hm = {(k, k): h[k] for k in range(c)} | {p: x for p, x in zip(f.pairs, h[c:])}
            gu = "+".join(f"({u[k]!r})*({g[k]})" for k in range(c) if u[k])
            hu = "+".join(f"({u[a] * u[b] * (1 if a == b else 2)!r})*({x})" for (a, b), x in hm.items() if u[a] and u[b])
            stats = f"{gu} AS g0, {hu} AS h0"
        else:
            stats = ", ".join([f"{x} AS g{k}" for k, x in enumerate(g)] + [f"{x} AS h{k}" for k, x in enumerate(h)])
        return f"{name} AS MATERIALIZED (SELECT node, test, b0, b1, b2, b3, {stats} FROM ({inner}) WHERE {where})"

    def vector(t: int, w: list[str]) -> list[str]:
        return [f"({w[0]}*({direction[t][1][k]!r}))" for k in range(c)] if scalar else w

    sums = ", ".join(f"sum({x}) AS {x}" for x in G + H)
    for t in range(trees):
        if t % snapshot == 0 and snapshot > 1:
            ctes.append(f"v{t} AS MATERIALIZED (SELECT {keep}, node, {s}, {', '.join(f's{k} AS r{k}' for k in range(c))} FROM {at})")
            at = f"v{t}"
        rest = ", ".join(f"r{k}" for k in range(c))
        ctes.append(f"t{t} AS MATERIALIZED (SELECT {keep}, {s}, {rest}, 1 AS node FROM {at})")
        at = f"t{t}"
        if layered and root:
            ctes.append(grads(f"gr{t}", at, t, "NOT test"))
            ctes.append(f"wr{t} AS (SELECT {', '.join(f'{eta}*{x} AS w{k}' for k, x in enumerate(vector(t, one.weight(G, H, 'n'))))} FROM (SELECT count(*) AS n, {sums} FROM gr{t}))")
            ctes.append(f"tr{t} AS MATERIALIZED (SELECT {keep}, node, {rest}, {', '.join(f's{k}+w{k} AS s{k}' for k in range(c))} FROM {at} CROSS JOIN wr{t})")
            at = f"tr{t}"
        frozen = at
        for d in range(depth):
            q = f"{t}_{d}"
            source = at
            ctes.append(grads(f"g{q}", source, t, f"NOT test AND node >= {2**d}"))
            ctes.append(f"c{q} AS (SELECT node, f, b, count(*) AS n, {sums} FROM (SELECT *, CASE f WHEN 0 THEN b0 WHEN 1 THEN b1 WHEN 2 THEN b2 ELSE b3 END AS b FROM g{q} CROSS JOIN (VALUES (0), (1), (2), (3)) AS k(f)) GROUP BY node, f, b)")
            over = "OVER (PARTITION BY node, f ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"
            all_ = "OVER (PARTITION BY node, f)"
            ctes.append(f"p{q} AS (SELECT node, f, b, {', '.join(f'sum({x}) {over} AS l{x}, sum({x}) {all_} AS t{x}' for x in ['n', *G, *H])} FROM c{q})")
            L, R, T = ([[f"l{x}" for x in v] for v in (G, H)], [[f"(t{x}-l{x})" for x in v] for v in (G, H)], [[f"t{x}" for x in v] for v in (G, H)])
            gain = f"round({one.gain(*L, 'ln')} + {one.gain(*R, '(tn-ln)')} - {one.gain(*T, 'tn')}, 9)"
            mean = lambda v: f"({f.scale}*({'+'.join(v[:width])})/{width})"
            ok = "ln < tn" + (f" AND {mean(L[1])} >= {min_child} AND {mean(R[1])} >= {min_child}" if min_child else "")
            wl, wr = vector(t, one.weight(*L, "ln")), vector(t, one.weight(*R, "(tn-ln)"))
            ctes.append(f"k{q} AS (SELECT node, f, b, tn, {gain} AS gain, {', '.join(f'{eta}*{x} AS wl{k}' for k, x in enumerate(wl))}, {', '.join(f'{eta}*{x} AS wr{k}' for k, x in enumerate(wr))} FROM p{q} WHERE {ok})")
            ctes.append(f"b{q} AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY gain DESC, f, b) AS i FROM k{q}) WHERE i = 1 AND gain > 0)")
            done.append(f"SELECT {t} AS tree, node, f AS feature, b AS bin, tn::BIGINT AS n, round(gain, 4) AS gain FROM b{q}")
            right = "(CASE k.f WHEN 0 THEN a.b0 WHEN 1 THEN a.b1 WHEN 2 THEN a.b2 ELSE a.b3 END > k.b)"
            node = f"CASE WHEN k.node IS NULL THEN a.node ELSE 2*a.node + {right}::INT END AS node"
            new = [f"a.s{i} + CASE WHEN k.node IS NULL THEN 0 WHEN {right} THEN k.wr{i} ELSE k.wl{i} END AS s{i}" for i in range(c)] if layered else [f"a.s{i}" for i in range(c)]
            cols = ", ".join("a." + x.strip() for x in keep.split(","))
            ctes.append(f"a{q} AS MATERIALIZED (SELECT {cols}, {', '.join(f'a.r{i}' for i in range(c))}, {', '.join(new)}, {node} FROM {at} a LEFT JOIN b{q} k ON a.node = k.node)")
            at = f"a{q}"
        if not layered:
            ctes.append(grads(f"gl{t}", at, t, "NOT test"))
            ctes.append(f"wl{t} AS (SELECT node, {', '.join(f'{eta}*{x} AS w{k}' for k, x in enumerate(vector(t, one.weight(G, H, 'n'))))} FROM (SELECT node, count(*) AS n, {sums} FROM gl{t} GROUP BY node))")
            cols = ", ".join("a." + x.strip() for x in keep.split(","))
            ctes.append(f"e{t} AS MATERIALIZED (SELECT {cols}, a.node, {', '.join(f'a.r{i}' for i in range(c))}, {', '.join(f'a.s{i} + coalesce(w.w{i}, 0) AS s{i}' for i in range(c))} FROM {at} a LEFT JOIN wl{t} w ON a.node = w.node)")
            at = f"e{t}"
        del frozen
    inner = f"SELECT *, {', '.join(f'{x} AS e{k}' for k, x in enumerate(helpers))} FROM {at}" if helpers else f"SELECT * FROM {at}"
    if kind == "class":
        sc = [f"s{k}" for k in range(c)]
        if f.loss == "marginexp":
            sc = ["(" + "+".join(f"({f.code(k, j)!r})*s{j}" for j in range(c)) + ")" for k in range(c)]
        best = "CASE " + " ".join(f"WHEN {sc[k]} = greatest({', '.join(sc)}) THEN {k}" for k in range(c)) + " END"
        hit = f"round(avg(({best} = y)::INT::DOUBLE), 4)"
    else:
        hit = "round(avg(((s0 >= 0)::INT = y)::INT::DOUBLE), 4)" if kind == "binary" else "NULL::DOUBLE"
    ctes.append(f"m AS (SELECT {hit} AS accuracy, round(avg({loss}), 4) AS test_loss FROM ({inner}) WHERE test)")
    if measured is None:
        return "WITH " + ",\n".join(ctes) + "\nSELECT * FROM m"
    if not measured:
        return "WITH " + ",\n".join(ctes) + "\n" + " UNION ALL ".join(done)
    return "WITH " + ",\n".join(ctes) + "\nSELECT d.*, m.accuracy, m.test_loss FROM (" + " UNION ALL ".join(done) + ") d CROSS JOIN m"


TWO = {"n_trees": 2, "depth": 2}


@query(booster_sql(Sql(3), 2, 2, 0.3))
def boost_diag_tree(spark, sf_dir):
    return told(spark, sf_dir, presets.diag(3, **TWO))


@query(booster_sql(Sql(3, hessian="full"), 2, 2, 0.3))
def boost_full_tree_c3(spark, sf_dir):
    return told(spark, sf_dir, presets.full(3, **TWO))


@query(booster_sql(Sql(3), 2, 2, 0.3, layered=True))
def boost_diag_lbl(spark, sf_dir):
    return told(spark, sf_dir, presets.diag_lbl(3, **TWO))


@query(booster_sql(Sql(3), 2, 2, 0.3, layered=True, root=False))
def boost_diag_lbl_noroot(spark, sf_dir):
    return told(spark, sf_dir, presets.diag_lbl(3, root_contributes=False, **TWO))


@query(booster_sql(Sql(3, hessian="full"), 2, 2, 0.3, layered=True))
def boost_full_lbl_c3(spark, sf_dir):
    return told(spark, sf_dir, presets.full_lbl(3, **TWO))


ONE = [[1.0 if j == k else 0.0 for j in range(3)] for k in range(3)]


@query(booster_sql(Sql(3), 3, 2, 0.3, direction=[(ONE[k], ONE[k]) for k in range(3)]))
def boost_tree_per_class(spark, sf_dir):
    return told(spark, sf_dir, presets.per_class(3, n_trees=3, depth=2))


@query(booster_sql(Sql(3), 3, 2, 0.3, layered=True, direction=[(ONE[k], ONE[k]) for k in range(3)]))
def boost_per_class_lbl(spark, sf_dir):
    """A tree per class whose layers are steps of their own."""
    return told(spark, sf_dir, presets.per_class_lbl(3, n_trees=3, depth=2))


def told_by_columns(spark, sf_dir, cfg: BoostConfig):
    """As told, by JvmRows: bins, scores, sums and splits are column expressions."""
    d = slice3(spark, sf_dir)
    names = [f"b{k}" for k in range(4)]
    rows = d.select("test", "y", *[bin_expr(c, e).alias(b) for b, c, e in zip(names, T3_FEATURES, T3_EDGES)])
    model = fit(JvmRows(rows.where("not test"), names), cfg, T3_EDGES)
    s = score_expr(model, T3_FEATURES)
    scored = d.where("test").select("y", *[x.alias(f"s{k}") for k, x in enumerate(s)])
    p, s = softmax_columns([F.col(f"s{k}") for k in range(3)]), [F.col(f"s{k}") for k in range(3)]
    best = F.when((s[0] >= s[1]) & (s[0] >= s[2]), 0).when(s[1] >= s[2], 1).otherwise(2)
    m = metrics.moments(scored.select("y", F.array(*p).alias("probability"), best.alias("prediction"))).first()
    out = [(t, j, int(x.feature[j]), int(x.bin[j]), int(x.n[j]), round(float(x.gain[j]), 4), round(m.accuracy, 4), round(m.cross_entropy, 4)) for t, x in enumerate(model.trees) for j in x.nodes() if x.feature[j] >= 0]
    return spark.createDataFrame(out, "tree int, node int, feature int, bin int, n long, gain double, accuracy double, test_loss double")


@query(booster_sql(Sql(3), 2, 2, 0.3, layered=True))
def jvm_diag_lbl(spark, sf_dir):
    return told_by_columns(spark, sf_dir, presets.diag_lbl(3, **TWO))


@query(booster_sql(Sql(3, hessian="full"), 2, 2, 0.3))
def jvm_full_tree_c3(spark, sf_dir):
    return told_by_columns(spark, sf_dir, presets.full(3, **TWO))


@query(booster_sql(Sql(3, scale=2.0), 3, 2, 0.3, direction=[(ONE[k], ONE[k]) for k in range(3)], snapshot=3, min_child=1.0))
def boost_ovr_round(spark, sf_dir):
    return told(spark, sf_dir, presets.per_class(3, refresh="round", n_trees=3, depth=2, hessian_scale=2.0, min_child_weight=1.0))


@query(booster_sql(Sql(1, loss="multilabel"), 2, 2, 0.3, kind="binary"))
def boost_binary_scalar(spark, sf_dir):
    return told(spark, sf_dir, BoostConfig(outputs=1, loss="logistic", **TWO), kind="binary")


@query(booster_sql(Sql(2, loss="squared"), 2, 2, 0.3, kind="real"))
def boost_vector_regression(spark, sf_dir):
    return told(spark, sf_dir, BoostConfig(outputs=2, loss="squared", **TWO), kind="real")


@query(booster_sql(Sql(2, loss="multilabel"), 2, 2, 0.3, kind="multi"))
def boost_multilabel(spark, sf_dir):
    return told(spark, sf_dir, BoostConfig(outputs=2, loss="multilabel", **TWO), kind="multi")


@query(booster_sql(Sql(3, loss="multiexp", hessian="identity", zero_sum=True), 2, 2, 0.3))
def preset_samme_like(spark, sf_dir):
    return told(spark, sf_dir, presets.samme_like(3, **TWO))


@query(booster_sql(Sql(3, loss="multiexp", hessian="least", lam=0), 2, 2, 0.3))
def preset_gamble_like(spark, sf_dir):
    """The summed Hessian is singular: the least-norm solution by SVD, in SQL by a closed form for three classes."""
    return told(spark, sf_dir, presets.gamble_like(3, **TWO))


@query(booster_sql(Sql(3, hessian="pair"), 2, 2, 0.3))
def preset_aoso_like(spark, sf_dir):
    return told(spark, sf_dir, presets.aoso_like(3, **TWO))


@query(booster_sql(Sql(3, loss="marginexp", hessian="identity"), 2, 2, 0.3))
def preset_gdmc_like(spark, sf_dir):
    return told(spark, sf_dir, presets.gd_mc_like(3, **TWO))


LOGIT = [(ONE[k], [2 / 3 * (ONE[k][j] - 1 / 3) for j in range(3)]) for k in range(3)]
ABC = [([ONE[k][j] - ONE[0][j] for j in range(3)],) * 2 for k in (1, 2)]


@query(booster_sql(Sql(3, lam=1e-6), 3, 2, 0.3, direction=LOGIT, snapshot=3))
def logitboost_round(spark, sf_dir):
    return told(spark, sf_dir, presets.per_class(3, refresh="round", n_trees=3, depth=2, lam=1e-6), how="logitboost")


@query(booster_sql(Sql(3, hessian="full", lam=1e-6), 2, 2, 0.3, direction=ABC, snapshot=2))
def abc_logitboost_round(spark, sf_dir):
    """Base class 0."""
    return told(spark, sf_dir, presets.per_class(3, refresh="round", n_trees=2, depth=2, lam=1e-6), how="abc", base_class=0)
