"""Toxicity of text behind a noisy channel.

Writers hide words by digits and signs for letters, by blanks between letters and by repeats. Suspicious
segments become character lattices of what may have been meant; a Viterbi search under a character language
model, counted over the whole corpus, picks the likeliest reading; a linear model scores the restored text.
Segments may be of any length: a run of one character is one step, and work grows with the steps.
A token without a doubtful character has a lattice of one path, so it is left as it is.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, spread

#: Character classes: 0 a boundary (anything else), 1 to 26 the letters, 27 any byte beyond ASCII.
CLASSES, ORDER = 28, 4
CLASS = np.zeros(256, np.int32)
CLASS[65:91] = CLASS[97:123] = np.arange(1, 27)
CLASS[128:] = 27
#: Letters that a sign may stand for.
MEANT = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "€": "e", "*": "aeiou"}
#: Costs (negative log probabilities) of the channel: sign for letter, sign as itself, run shortened, run kept, gap as word end, two letters for one.
SWAP, ITSELF, SHORTEN, KEEP_RUN, GAP, DOUBLED = 0.7, 3.0, 0.5, 2.0, 2.5, 3.0
SPACED = re.compile(r"(?<![^\W_])(?:[A-Za-z0-9@$!|+*][ ._\-]{1,2}){3,}[A-Za-z0-9@$!|+*](?![^\W_])")
PIECES = re.compile(r"[^\s.,;:?\"()\[\]{}<>/\\#%&=_-]+")
MIXED = re.compile(r"[^\W\d_][0-9@$!|+*]|[0-9@$!|+*][^\W\d_]")
TWO, LETTERS = re.compile(r"(?i)([a-z])\1"), re.compile(r"[^\W\d_]+")
RUN = re.compile(r"(?s)(.)\1+")
SIGNS = set("0123456789@$!|+*")
WORDS, ENDS = LETTERS, ".,;:?\"'()"
#: Bounds of training: labelled rows, features of the linear model, and the log likelihood ratio that a feature brings.
SAMPLE, N_FEATURES, LEAST_GAIN = 20_000, 4_000, 12.0


def class_codes(text: bytes) -> np.ndarray:
    """Codes of the ORDER-grams of classes, runs of boundaries taken as one."""
    c = CLASS[np.frombuffer(text, np.uint8)]
    c = c[np.concatenate([[True], (c[1:] != 0) | (c[:-1] != 0)])] if len(c) else c
    n = len(c) - ORDER + 1
    code = np.zeros(max(n, 0), np.int32)
    for k in range(ORDER):
        code = code * CLASSES + c[k : k + max(n, 0)]
    return code


def gram_counts(docs: DataFrame, text: str = "text") -> np.ndarray:
    """Counts of all ORDER-grams over all texts: partial sums in every task, CLASSES**ORDER cells at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CLASSES**ORDER, np.int64)
        for b in batches:
            held, size = [], 0
            for t in b.column("text").cast(pa.binary()).to_pylist() + [None]:
                if t:
                    held.append(t)
                    size += len(t)
                if held and (t is None or size > 1 << 20):
                    total += np.bincount(class_codes(b"\n" + b"\n\n".join(held) + b"\n"), minlength=len(total))
                    held, size = [], 0
        cells = np.nonzero(total)[0]
        yield pa.RecordBatch.from_pydict({"code": pa.array(cells, pa.int32()), "n": pa.array(total[cells], pa.int64())})

    sums = spread(docs.select(F.col(text).alias("text"))).mapInArrow(run, "code int, n long").groupBy("code").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(CLASSES**ORDER, np.float64)
    out[sums["code"].to_numpy()] = sums["n"].to_numpy()
    return out


def language_model(counts: np.ndarray, mass: float = 4.0) -> np.ndarray:
    """-log P(class | the three before), each order smoothed by the one below it."""
    c4 = counts.reshape((CLASSES,) * ORDER)
    p = np.full(CLASSES, 1 / CLASSES)
    for k in range(1, ORDER + 1):
        c = c4.sum(axis=tuple(range(ORDER - k))) if k < ORDER else c4
        p = (c + mass * p) / (c.sum(axis=-1, keepdims=True) + mass)
    return (-np.log(p)).astype(np.float32).ravel()


def lattice(segment: str) -> list[list[tuple[tuple[int, ...], float]]]:
    """Steps of (classes put out, cost), one for each run of a character."""
    steps: list = []
    spaced, before, times = bool(SPACED.fullmatch(segment)), "", 0
    for m in re.finditer(r"(?s)(.)\1*", segment.lower()):
        c, n = m[1], len(m[0])
        if spaced and c in " ._-":
            steps.append([((), 0.0), ((0,), GAP if n == 1 and "  " not in segment else 0.3)])
            continue
        own = int(CLASS[ord(c)]) if ord(c) < 128 else 27
        joined = [((), SHORTEN)] if max(n, times) > 2 and (c in MEANT.get(before, "") or before and before in MEANT.get(c, "")) else []  # a sign and a run of its letter
        before, times = c, n
        if own:
            kept = [((own,) * n, 0.0)] + [((own,), DOUBLED)] * (n == 2 and own < 27)
            steps.append(joined + (kept if n < 3 else [((own,), SHORTEN), ((own,) * 2, SHORTEN), ((own,) * n, KEEP_RUN)]))
            continue
        said = [((ord(x) - 96,) * k, SWAP + (0.0 if k == n else SHORTEN)) for x in MEANT.get(c, "") for k in {1, min(n, 2)}]
        steps.append(joined + said + [((0,), ITSELF if said else 0.0)])
    return steps


def decode(segment: str, cost: list[float]) -> str:
    """The likeliest reading (Viterbi; the state is the last three classes)."""
    best: dict = {(0, 0, 0): (0.0, None)}  # what was said is a chain from its end, shared by the paths
    for step in [*lattice(segment), [((0,), 0.0)]]:
        after: dict = {}
        for (a, b, c), (total, said) in best.items():
            for out, own in step:
                x, y, z, t, s = a, b, c, total + own, said
                for d in out:
                    if d or z:
                        t += cost[((x * CLASSES + y) * CLASSES + z) * CLASSES + d]
                        x, y, z = y, z, d
                        s = (s, d)
                if (x, y, z) not in after or t < after[x, y, z][0]:
                    after[x, y, z] = (t, s)
        best = after
    said, letters = min(best.items(), key=lambda kv: (kv[1][0], kv[0]))[1][1], []
    while said:
        said, d = said
        letters.append(" " if d == 0 else "é" if d == 27 else chr(96 + d))
    return "".join(reversed(letters)).strip()


def spaced_out(text: str) -> list[str]:
    """Runs of four or more single signs with gaps between, of three different ones at least."""
    return [m[0] for m in SPACED.finditer(text) if len(set(re.sub(r"[ ._\-]", "", m[0].lower()))) > 2]


def bare(s: str) -> str:
    """s without the signs at its ends that may be punctuation: any ! * | + after it, any * | + before it, and doubled ones."""
    if len(s) < 3:
        return s
    if s[0] in SIGNS:
        s = s.lstrip(s[0] if s[1] == s[0] else "*|+")
    if s and s[-1] in SIGNS:
        s = s.rstrip("!*|+" if s[-1] in "!*|+" else s[-1] if s[-2:-1] == s[-1] else "")
    return s


def doubtful(token: str) -> list[str]:
    """Segments of a blank-free token whose lattices have more than one path; with and without the signs at their ends."""
    found = []
    if not token.isalpha():
        for m in PIECES.finditer(token):
            if MIXED.search(m[0]):
                core = bare(m[0])
                found += [m[0], core] if core != m[0] and MIXED.search(core) else [m[0]]
    if TWO.search(token):
        found += [m[0] for m in LETTERS.finditer(token) if TWO.search(m[0])]
    return found


LOOK = np.zeros(256, np.uint8)
LOOK[list(b" \t\r\n._-")] = 1
LOOK[[*range(48, 58), *range(65, 91), *range(97, 123), *b"@$!|+*"]] = 2


def may_be_spaced(b: bytes) -> bool:
    """Whether four signs follow each other over gaps of one or two; true wherever SPACED matches, a quick look before it."""
    c = LOOK[np.frombuffer(b + bytes(9), np.uint8)]
    sign, gap = c == 2, c == 1
    one, two = sign[:-3] & gap[1:-2] & sign[2:-1], sign[:-3] & gap[1:-2] & gap[2:-1] & sign[3:]
    far = one | two
    for _ in range(2):
        far = one[: len(far) - 3] & far[2:-1] | two[: len(far) - 3] & far[3:]
    return bool(far.any())


def shrink(s: str) -> str:
    """s with every run one character long."""
    return RUN.sub(r"\1", s)


class Reader:
    """Telling features of texts, restored first; readings and verdicts on tokens are kept in bounded tables."""

    def __init__(self, cost: np.ndarray, wanted: set[str] | None = None, most: int = 600_000):
        self.cost, self.wanted, self.most, self.dull, self.telling = cost.tolist(), wanted, most, set(), {}
        self.starts = None if wanted is None else {f[:4] for f in wanted if f[:4].isalpha() or len(f) > 4}
        self.shrunk = None if wanted is None else {shrink(x) for x in self.starts}
        self.short = None if wanted is None else {shrink(f[:-1]) for f in wanted if f.endswith("$") and len(f) < 5}

    def may_matter(self, s: str) -> bool:
        """Whether some reading of a segment of plain letters could be a wanted feature: readings only change how long its
        runs are, so they are the same once all runs are one letter long."""
        if self.wanted is None or not (s.isascii() and s.isalpha()):
            return True
        t = shrink(s)
        return t in self.short or any(t[:k] in self.shrunk for k in range(1, 5))

    def of_word(self, w: str) -> list[str]:
        if self.starts is not None and len(w) >= 4 and w[:4] not in self.starts:
            return []
        own = [w + "$", *(w[:k] for k in range(4, min(len(w), 9)))]
        return own if self.wanted is None else [f for f in own if f in self.wanted]

    def of_token(self, token: str) -> tuple[str, ...]:
        token = token.strip(ENDS)
        words = [token] if token.isalpha() else WORDS.findall(token)
        for s in doubtful(token):
            if self.may_matter(s):
                words += decode(s, self.cost).split()
        return tuple(f for w in words for f in self.of_word(w))

    def features(self, raw: bytes) -> set[str]:
        text = raw.decode()
        tokens, out = set(text.lower().split()), set()
        if may_be_spaced(raw):
            for s in set(spaced_out(text)):
                tokens.update(decode(s, self.cost).split())
        for token in tokens - self.dull:
            own = self.telling.get(token)
            if own is None:
                own = self.of_token(token)
                if own:
                    if len(self.telling) >= self.most // 10:
                        self.telling.clear()
                    self.telling[token] = own
                else:
                    if len(self.dull) >= self.most:
                        self.dull = set()
                    self.dull.add(token)
            out.update(own)
        return out


def restore(text: str, cost: list[float]) -> str:
    """The text with every doubtful segment read anew; for people to see. Signs that are read as punctuation stay."""

    spaced, found = set(spaced_out(text)), {s for t in text.split() for s in doubtful(t.strip(ENDS))}
    for s in sorted(spaced, key=lambda x: (-len(x), x)):
        text = text.replace(s, decode(s, cost))
    read = {s: decode(s, cost) for s in found}
    for s in sorted(found, key=lambda x: (-len(x), x)):
        core = bare(s)
        as_is = re.sub(r"[^\x00-\x7f]", "é", " ".join(WORDS.findall(core.lower())))
        if read[s] != as_is and (core == s or read[s] != read.get(core)):
            text = re.sub(rf"(?<![^\W\d_]){re.escape(s)}(?![^\W\d_])", read[s], text)
    return text


@dataclass
class ToxicityModel:
    cost: np.ndarray  # of the language model
    weights: dict[str, float]
    bias: float

    def scorer(self):
        reader, weights = Reader(self.cost, set(self.weights)), self.weights

        def score(raw: bytes) -> float:
            z = self.bias + sum(weights[f] for f in sorted(reader.features(raw)))
            return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))

        return score


def held_out(id_col: str):
    """crc32 of the id as text, modulo 5, is 0."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0


def regress(x: list[list[int]], y: np.ndarray, n: int, l2: float = 1.0, steps: int = 1000) -> tuple[np.ndarray, float]:
    """Logistic regression on 0/1 features by gradient steps with momentum, classes weighted alike."""
    rows = np.repeat(np.arange(len(x)), [len(r) for r in x])
    cols = np.array([c for r in x for c in r], np.int64)
    w, b, v, vb = np.zeros(n), 0.0, np.zeros(n), 0.0
    weight = np.where(y == 1, 0.5 / max(1, y.sum()), 0.5 / max(1, (1 - y).sum()))
    scale = 8.0 / max(1.0, np.mean([len(r) for r in x]) if x else 1.0)
    for _ in range(steps):
        z = b + np.bincount(rows, w[cols], len(x))
        g = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) * weight
        v = 0.9 * v - scale * (np.bincount(cols, g[rows], n) + l2 * w / max(1, len(x)) / 10)
        vb = 0.9 * vb - scale * g.sum()
        w, b = w + v, b + vb
    return w, float(b)


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "toxic", sample: int = SAMPLE, n_features: int = N_FEATURES) -> ToxicityModel:
    """Counts the language model over all texts; fits the scorer on at most `sample` labelled rows that aren't held out."""
    cost = language_model(gram_counts(docs, text))
    some = labels.where(F.col(id_col).isNotNull() & F.col(label).isin(0, 1) & ~held_out(id_col)).groupBy(id_col).agg(F.max(label).alias("_y"))
    some = some.orderBy(F.xxhash64(id_col), id_col).limit(sample)  # bounds what is broadcast and collected
    known = docs.select(F.col(id_col).alias("_id"), F.col(text).alias("text")).join(F.broadcast(some.withColumnRenamed(id_col, "_id")), "_id")
    known = known.repartition(4 * docs.sparkSession.sparkContext.defaultParallelism, "_id")
    known = cut(known.groupBy("_id", "_y").agg(F.min("text").alias("text")).select("text", "_y"))  # a text an id, so `sample` at most

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader, seen = Reader(cost), (Counter(), Counter())
        for b in batches:
            for raw, y in zip(b.column("text").cast(pa.binary()).to_pylist(), b.column("_y").to_pylist()):
                seen[y].update(reader.features(raw or b"") | {"\n"})
        keys = list(seen[0].keys() | seen[1].keys())
        yield pa.RecordBatch.from_pydict({"f": pa.array(keys, pa.string()), "good": pa.array([seen[0][k] for k in keys], pa.int64()), "bad": pa.array([seen[1][k] for k in keys], pa.int64())})

    told = known.mapInArrow(count, "f string, good long, bad long").groupBy("f").agg(F.sum("good").alias("good"), F.sum("bad").alias("bad")).where("bad >= 3 or f = '\n'")
    told = cut(told)
    both = told.where("f = '\n'").first()
    if both is None or not both.good or not both.bad:
        return ToxicityModel(cost, {}, -10.0)
    rate = (F.col("bad") + 0.5) / (both.bad + 1) / ((F.col("good") + 0.5) / (both.good + 1))
    chosen = [r.f for r in told.where("f <> '\n'").select("f", (F.col("bad") * F.log(rate)).alias("gain")).where(rate > 2).where(f"gain >= {LEAST_GAIN}").orderBy(F.desc("gain"), "f").limit(n_features).collect()]
    place = {f: k for k, f in enumerate(chosen)}

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(cost, set(place))
        for b in batches:
            x = [sorted(place[f] for f in reader.features(raw or b"")) for raw in b.column("text").cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_pydict({"x": pa.array(x, pa.list_(pa.int32())), "y": b.column("_y").cast(pa.int32())})

    data = known.mapInArrow(rows, "x array<int>, y int").toPandas()
    x = [list(r) for r in data["x"]]
    order = sorted(range(len(x)), key=lambda k: (x[k], data["y"].iat[k]))  # the sums don't depend on how rows were dealt
    w, bias = regress([x[k] for k in order], data["y"].to_numpy(np.float64)[order], len(place))
    return ToxicityModel(cost, {f: float(w[k]) for f, k in place.items() if w[k]}, bias)


def score_toxicity(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", model: ToxicityModel | None = None, **options) -> DataFrame:
    """(id, held_out, score, predicted) for every row, from its whole text alone.

    Null and empty texts get the score of a text without telling words. Without labels of both kinds every
    score is near zero. Null ids and repeated rows each get a row (a null id is not held out); an empty table gives none; other
    columns, whatever their names, are not read.
    """
    model = fit(docs, labels, id_col, text, **options) if model is None else model
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = model.scorer()
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([score(t or b"") for t in b.column("text").cast(pa.binary()).to_pylist()], pa.float64())], ["id", "score"])

    scored = spread(docs.select(F.col(id_col).alias("id"), F.col(text).alias("text"))).mapInArrow(run, f"id {kind}, score double")
    return scored.select(F.col("id").alias(id_col), F.coalesce(held_out("id"), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", model: ToxicityModel | None = None, **options) -> DataFrame:
    """docs, all columns, without the rows whose text scores 0.5 or more; decided row by row, in one pass.

    Null and empty texts score as texts without telling words; null ids and repeated rows are judged each by its text;
    columns of any names pass through; an empty table gives no rows.
    """
    model = fit(docs, labels, id_col, text, **options) if model is None else model

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = model.scorer()
        for b in batches:
            yield b.filter(pa.array([score(t or b"") < 0.5 for t in b.column(text).cast(pa.binary()).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
