"""Learned quality rules: an ordered list of threshold conjunctions, found by sequential covering.

Text statistics come from one pass; a bounded sample of labelled rows trains the list (grow on two thirds,
prune on one third), and the list is applied as nested Spark conditionals, so its reading is its code.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import spread

BLANK, SYMBOLS = b" \t\n\r\x0b\x0c", b"#*$%&|<>"
UPPER, DIGITS = bytes(range(65, 91)), bytes(range(48, 58))
MARKS = b"!?.,;:-_\"'()[]{}/\\+=@~^`"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_upper", "n_digits", "n_marks", "n_lines"]
#: What rules may test: name to SQL over the counts.
FEATURES = {
    "words": "n_words",
    "chars_per_word": "word_chars / greatest(n_words, 1)",
    "symbols_per_word": "n_symbols / greatest(n_words, 1)",
    "dup_line_share": "n_dup_lines / greatest(n_lines, 1)",
    "repeat_share": "n_repeat_words / greatest(n_words, 1)",
    "upper_share": "n_upper / greatest(word_chars, 1)",
    "digit_share": "n_digits / greatest(word_chars, 1)",
    "marks_per_word": "n_marks / greatest(n_words, 1)",
    "words_per_line": "n_words / greatest(n_lines, 1)",
}
BASE_FAILED = "n_words < 50 or 100 * n_repeat_words > 50 * n_words"


def repeat_words(words: list[bytes]) -> int:
    """Words that lie in a 3-word window found twice or more in the text."""
    if len(words) < 4:
        return 0
    seen: dict[bytes, int] = {}
    ids = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
    v = len(seen)
    if v >= 2_000_000:  # beyond this three ids don't fit in 63 bits
        pair = np.unique(ids[:-1] * v + ids[1:], return_inverse=True)[1]
        key = pair[:-1] * v + ids[2:]
    else:
        key = (ids[:-2] * v + ids[1:-1]) * v + ids[2:]
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    hit = np.zeros(len(key), bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    inside = np.zeros(len(words), bool)
    for k in range(3):
        inside[k : len(words) - 2 + k] |= hit
    return int(inside.sum())


def counts(text: bytes, n_chars: int) -> tuple[int, ...]:
    words = text.split()
    without = lambda cut: len(text) - len(text.translate(None, cut))
    lines = [x for x in text.split(b"\n") if x.strip(BLANK)]
    return (len(words), n_chars - without(BLANK), without(SYMBOLS), len(lines) - len(set(lines)), repeat_words(words), without(UPPER), without(DIGITS), without(MARKS), len(lines))


def statistics(docs: DataFrame, id_col: str = "doc_id", text: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """(id, *carry, *COUNTS) for every row, over whole texts; a null text counts as empty."""
    kinds = dict(docs.dtypes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            column = pc.fill_null(b.column("_text"), "")
            rows = [counts(t, n) for t, n in zip(column.cast(pa.binary()).to_pylist(), pc.utf8_length(column).to_pylist())]
            cols = list(zip(*rows)) or [()] * len(COUNTS)
            yield pa.RecordBatch.from_arrays([b.column(c) for c in (id_col, *carry)] + [pa.array(c, pa.int64()) for c in cols], [id_col, *carry, *COUNTS])

    read = spread(docs.select(id_col, *carry, F.col(text).alias("_text")))
    return read.mapInArrow(run, ", ".join([f"`{c}` {kinds[c]}" for c in (id_col, *carry)] + [f"{c} long" for c in COUNTS]))


@dataclass(frozen=True)
class Test:
    feature: str
    above: bool
    value: float

    def sql(self) -> str:
        return f"{FEATURES[self.feature]} {'>' if self.above else '<='} {self.value!r}D"


def covers(rule: list[Test], x: dict[str, np.ndarray]) -> np.ndarray:
    out = np.ones(len(next(iter(x.values()))), bool)
    for t in rule:
        out &= (x[t.feature] > t.value) == t.above
    return out


def grow(x: dict[str, np.ndarray], bad: np.ndarray, cuts: dict[str, np.ndarray], most: int) -> list[Test]:
    """Adds the test of the largest information gain until a rule covers no good row or nothing gains."""
    rule, held = [], np.ones(len(bad), bool)
    while len(rule) < most:
        p0, n0 = (held & bad).sum(), (held & ~bad).sum()
        if not n0 or not p0:
            break
        best, gain = None, 1e-9
        for f, values in cuts.items():
            v = x[f][held]
            order = np.argsort(v, kind="stable")
            at = np.searchsorted(v[order], values, side="right")
            pos = np.concatenate([[0], np.cumsum(bad[held][order])])
            for above in (False, True):
                p = pos[-1] - pos[at] if above else pos[at]
                n = (len(v) - at if above else at) - p
                g = np.where(p > 0, p * (np.log2(np.maximum(p, 1) / np.maximum(p + n, 1)) - np.log2(p0 / (p0 + n0))), 0)
                k = int(np.argmax(g))
                if g[k] > gain:
                    best, gain = Test(f, above, float(values[k])), g[k]
        if best is None:
            break
        rule.append(best)
        held = covers(rule, x)
    return rule


def centred(rule: list[Test], x: dict[str, np.ndarray]) -> list[Test]:
    """Each threshold moved to the middle of the gap between the values next to it, which changes no row seen."""
    out = []
    for k, t in enumerate(rule):
        others = covers(rule[:k] + rule[k + 1 :], x) if len(rule) > 1 else np.ones(len(x[t.feature]), bool)
        v = x[t.feature][others]
        low, high = v[v <= t.value], v[v > t.value]
        out.append(Test(t.feature, t.above, float((low.max() + high.min()) / 2)) if len(low) and len(high) else t)
    return out


def learn(x: dict[str, np.ndarray], bad: np.ndarray, max_rules: int = 12, max_tests: int = 4, precision: float = 0.8, n_cuts: int = 64, seed: int = 5) -> list[list[Test]]:
    """Rules for bad rows, in order. Each is grown on two thirds of what is left, pruned on the rest by
    (p - n) / (p + n), and kept while it is right often enough there; then what it covers is taken away."""
    left, rng, rules = np.ones(len(bad), bool), np.random.default_rng(seed), []
    if not len(bad):
        return rules
    cuts = {f: np.unique(np.quantile(v, np.linspace(0, 1, n_cuts + 1)[1:-1])) for f, v in x.items()}
    part = rng.random(len(bad)) < 2 / 3
    while len(rules) < max_rules and (left & bad & part).any():
        g, r = left & part, left & ~part
        rule = grow({f: v[g] for f, v in x.items()}, bad[g], cuts, max_tests)
        if not rule:
            break
        rest, worth = {f: v[r] for f, v in x.items()}, []
        for k in range(1, len(rule) + 1):
            hit = covers(rule[:k], rest)
            p, n = (hit & bad[r]).sum(), (hit & ~bad[r]).sum()
            worth.append(((p - n) / (p + n) if p + n else -1, -k))
        rule = rule[: -max(worth)[1]]
        hit = covers(rule, rest)
        p, n = (hit & bad[r]).sum(), (hit & ~bad[r]).sum()
        if not p or p < precision * (p + n):
            break
        rule = centred(rule, {f: v[left] for f, v in x.items()})
        rules.append(rule)
        left &= ~covers(rule, x)
    return rules


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "quality", sample: int = 20_000, **options) -> list[list[Test]]:
    """Learns from at most `sample` labelled rows (the least hashes of their ids); label 1 is good, 0 bad."""
    some = labels.where(F.col(id_col).isNotNull() & F.col(label).isin(0, 1)).groupBy(id_col).agg(F.min(label).alias("_y"))
    some = some.orderBy(F.xxhash64(id_col), id_col).limit(sample)  # bounds what is broadcast and collected
    known = statistics(docs.select(id_col, text).join(F.broadcast(some), id_col), id_col, text, ("_y",))
    usable = known.where(f"not ({BASE_FAILED})").selectExpr(f"`{id_col}` as i", "_y", *[f"cast({e} as double) as {f}" for f, e in FEATURES.items()])
    rows = usable.groupBy("i", "_y").agg(F.min(F.struct(*FEATURES)).alias("f")).select("i", "_y", "f.*").toPandas().sort_values("i")  # a row an id, so `sample` at most
    return learn({f: rows[f].to_numpy(np.float64) for f in FEATURES}, rows["_y"].to_numpy() == 0, **options)


def verdict(rules: list[list[Test]]):
    """The list as one ordered conditional: the first rule that fits says no, else yes."""
    out = None
    for k, rule in enumerate(rules):
        hit = F.expr(" and ".join(f"({t.sql()})" for t in rule))
        out = F.when(hit, F.lit(k)) if out is None else out.when(hit, F.lit(k))
    return F.lit(-1) if out is None else out.otherwise(F.lit(-1))


def judge_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "quality", rules: list[list[Test]] | None = None, **options) -> DataFrame:
    """(id, counts, base_failed, rule, kept) for every row: kept unless base_failed or a learned rule fits.

    rule is the position of the first rule that fits, -1 for none. A null text counts as empty (base_failed).
    Without usable labels the list is empty and only the base rule decides. Repeated rows each get a row, null
    ids too; an empty table gives none; other columns, whatever their names, are not read.
    """
    rules = fit(docs, labels, id_col, text, label, **options) if rules is None else rules
    s = statistics(docs, id_col, text).withColumn("base_failed", F.expr(BASE_FAILED)).withColumn("rule", verdict(rules))
    return s.withColumn("kept", ~F.col("base_failed") & (F.col("rule") < 0))
