"""Each operator against brute force, on small tables with nulls, blanks, ties, repeats, long texts and clashing columns."""

import hashlib
import io
import random
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from vecboost.llm import near_copies, quality, simhash, suffix_dedup, toxicity
from vecboost.llm.common import components, prefix_sums
from vecboost.llm.embed_dedup import link_vectors, quantise, tile_links, unit
from vecboost.llm.mixing import DOMAIN_WEIGHTS, LANGUAGE_WEIGHTS, Node, budgets, mix, share, take_mix
from vecboost.llm.packing import optimal_bounds, pack
from vecboost.llm.suffix_dedup import anchors, cut_passages, passage_digests, suffix_order
from vecboost.llm.tokens import Encoder, PlaneReader, PlaneWriter, token_digests
from vecboost.llm.url_rules import RULES, PathRules, judge_urls
from vecboost.llm.warc import archive_digest, archive_pages, read_archives

WORDS = "the of and nation river stone light under seven paper green cloud idiot moron".split()
rnd = random.Random(2)
LONG = " ".join(rnd.choice(WORDS) + str(k % 97) for k in range(6000))
COPY = " ".join(rnd.choice(WORDS) + str(k) for k in range(40))
TEXTS = [None, "", "  \n\t ", "one", "one two", COPY, COPY, COPY.replace("40", "41") + " x", LONG, LONG + " tail", "a b c a b c a b c", "É!! " * 9, "x # $ % & | < >\nx\n\nx\n", "word word word word", COPY.upper()]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(k, t, "en", f"src{k % 3}", len(t or ""), "clash") for k, t in enumerate(TEXTS)] + [(5, COPY, "en", "src1", 3, "again"), (None, "no id", None, None, None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score string").repartition(3)


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def union_find(nodes, links):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def test_components_and_prefix_sums(spark):
    edges = [(k, k + 1) for k in range(30)] + [(100, 200), (200, 150), (7, 7), (5, None)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: 0 for k in range(1, 31)} | {200: 100, 150: 100}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
    d = spark.createDataFrame([(k % 2, k, k + 1) for k in range(50)] + [(None, 1, 5), (None, 2, 6)], "g long, o long, v long")
    got = {(r.g, r.o): r.s for r in prefix_sums(d, ["g"], ["o"], "v", "s", 5).collect()}
    assert got[0, 48] == sum(range(1, 48, 2)) and got[None, 2] == 5 and got[1, 1] == 0


def base_counts(text):
    words = (text or "").encode().split()
    tri = [tuple(words[k : k + 3]) for k in range(len(words) - 2)]
    inside = {k + j for k, t in enumerate(tri) if tri.count(t) > 1 for j in range(3)}
    lines = [x for x in (text or "").encode().split(b"\n") if x.split()]
    return len(words), sum(len(w.decode()) for w in words), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(inside)


def test_quality_counts_and_rules(spark, docs, none):
    small = docs.where("doc_id is null or doc_id not in (8, 9)")
    labels = spark.createDataFrame([(k, int(k % 2)) for k in range(15)], "doc_id long, quality int")
    rows = quality.judge_quality(small, labels).collect()
    texts = dict(enumerate(TEXTS)) | {None: "no id"}
    for r in rows:
        n = base_counts(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == n
        assert r.base_failed == (n[0] < 50 or 100 * n[4] > 50 * n[0])
    assert len(rows) == 15 and quality.judge_quality(none, labels).count() == 0
    rng = np.random.default_rng(0)
    x = {"a": rng.random(3000), "b": rng.random(3000)}
    bad = (x["a"] > 0.7) & (x["b"] <= 0.4) | (x["a"] < 0.1)
    rules = quality.learn(x, bad, n_cuts=200)
    got = np.zeros(3000, bool)
    for rule in rules:
        got |= quality.covers(rule, x)
    assert (got == bad).mean() > 0.97 and len(rules) <= 6
    assert quality.learn({"a": np.zeros(0)}, np.zeros(0, bool)) == []


def test_the_conditional_says_what_the_rules_say(spark):
    r = random.Random(8)
    texts = ["\n".join(" ".join(r.choice(["aa", "B1", "#x", "...", "word", "Zz9!"]) for _ in range(r.randint(1, 30))) for _ in range(r.randint(1, 6))) for _ in range(150)] + ["", None]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    test = quality.Test
    rules = [[test("symbols_per_word", True, 0.3), test("words", False, 60.0)], [test("upper_share", True, 0.15)], [test("dup_line_share", False, 0.0), test("digit_share", True, 0.1), test("marks_per_word", True, 0.4)]]
    rows = quality.judge_quality(d, None, rules=rules).collect()
    x = {f: np.array([eval(e.replace("greatest", "max"), {"max": max}, q.asDict()) for q in rows], float) for f, e in quality.FEATURES.items()}
    first = np.full(len(rows), -1)
    for k in reversed(range(3)):
        first[quality.covers(rules[k], x)] = k
    assert [q.rule for q in rows] == first.tolist() and set(first) >= {-1, 0, 1}
    assert all(q.kept == (not q.base_failed and q.rule < 0) for q in rows)


def brute_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = [w.decode() for w in low.encode().split()]
    if not words:
        return 0
    sh = [" ".join(words[k : k + 3]) for k in range(len(words) - 2)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash(spark, docs, none):
    small = docs.where("doc_id is null or doc_id not in (8, 9)")
    rows = simhash.near_duplicates(small).collect()
    texts = dict(enumerate(TEXTS)) | {None: "no id"}
    assert all(int(r.fingerprint, 16) == brute_fingerprint(texts[r.doc_id]) for r in rows) and len(rows) == 15
    ids = sorted({r.doc_id for r in rows if r.doc_id is not None})
    fp = {i: brute_fingerprint(texts[i]) for i in ids}
    root = union_find(ids, [(a, b) for a in ids for b in ids if a < b and bin(fp[a] ^ fp[b]).count("1") <= 3])
    assert {r.doc_id: r.component_id for r in rows if r.doc_id is not None} == root
    kept = [r.doc_id for r in simhash.keep_one(small).collect()]
    assert set(k for k in kept if k is not None) == set(root.values()) and None in kept
    assert simhash.near_duplicates(none).count() == 0


def test_vantage_trees_find_every_pair(spark, monkeypatch):
    rng = np.random.default_rng(5)
    centres = rng.integers(0, 2**63, 60, np.uint64)
    p = centres[rng.integers(0, 60, 1500)]
    for _ in range(4):
        p ^= np.where(rng.random(1500) < 0.6, np.uint64(1) << rng.integers(0, 64, 1500).astype(np.uint64), np.uint64(0)).astype(np.uint64)
    p = np.unique(p)
    monkeypatch.setattr(simhash, "PER_SHARD", 64)
    i, j = np.nonzero(np.triu(np.bitwise_count(p[:, None] ^ p[None, :]) <= 3, 1))
    want = union_find(range(len(p)), zip(i.tolist(), j.tolist()))
    d = spark.createDataFrame([(int(v), k, 1) for k, v in enumerate(p.view(np.int64))], "fp long, node long, n long").repartition(4)
    got = {r.node: r.root for r in simhash.link(d).collect()}
    assert {k: got.get(k, k) for k in range(len(p))} == want
    monkeypatch.setattr(simhash, "PER_SHARD", 8)  # leaves with many more visitors than members: several pieces
    monkeypatch.setattr(simhash, "VISITORS", 1)
    sample = np.sort(p)
    tree = simhash.grow(sample, 7)
    assert simhash.pieces_of(tree, sample, 3)
    got = {r.node: r.root for r in simhash.link(d).collect()}
    assert {k: got.get(k, k) for k in range(len(p))} == want


def test_pipeline_drops_edited_copies(spark, docs, none, monkeypatch):
    import corpus_pipeline as P

    r, texts = random.Random(4), dict(enumerate(TEXTS))
    for k in range(12):
        base = [f"{r.choice(WORDS)}{r.randint(0, 500)}" for _ in range(r.choice([60, 120, 300]))]
        texts[100 + 10 * k] = " ".join(base)
        for j in range(1, 9):
            edited = list(base)
            for at in r.sample(range(len(base)), 1 + j % 3):
                edited[at] = f"new{k}x{j}"
            texts[100 + 10 * k + j] = " ".join(edited)
    words = {i: (t or "").lower().encode().split() for i, t in texts.items()}
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set() for i, w in words.items()}
    close = [(a, b) for a in sets for b in sets if a < b and (sets[a] == sets[b] or 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]))]
    root = union_find(sets, close)
    far = [(a, b) for a, b in close if a >= 100 and bin(brute_fingerprint(texts[a]) ^ brute_fingerprint(texts[b])).count("1") > 3]
    assert len(far) > 50  # op2's links alone would miss these
    monkeypatch.setattr(near_copies, "BLOCK", 3)  # clusters of several tiles
    d = spark.createDataFrame([*texts.items(), (5, COPY), (None, "no id")], "doc_id long, text string").repartition(4)
    got = near_copies.near_copies(d).collect()
    assert {r.doc_id: r.component_id for r in got if r.doc_id is not None} == root and len(got) == len(texts) + 2
    kept = [r.doc_id for r in P.near_duplicates(spark, d, "").collect()]
    assert sorted(k for k in kept if k is not None) == sorted([*set(root.values()), 5]) and None in kept
    assert near_copies.near_copies(none).count() == 0


def test_embeddings(spark):
    rng = np.random.default_rng(3)
    c = rng.normal(size=(12, 16))
    x = (c[rng.integers(0, 12, 150)] + rng.normal(size=(150, 16)) * 0.22).tolist()
    x += [x[0], x[0], None, [0.0] * 16, [float("nan")] + [1.0] * 15, [None] + [1.0] * 15, [1e200] * 16, [2.0 * v for v in x[1]]]
    d = spark.createDataFrame([(k, v, 0) for k, v in enumerate(x)], "vec_id long, embedding array<double>, label int").repartition(3)
    rows = {r.vec_id: r for r in link_vectors(d, block=40).collect()}
    ok = {k: unit(np.array([v]))[0] for k, v in enumerate(x) if v and all(u is not None and np.isfinite(u) for u in v) and any(v)}
    links = [(a, b) for a in ok for b in ok if a < b and ok[a] @ ok[b] >= 0.95]
    root = union_find(range(len(x)), links)
    for k in range(len(x)):
        assert rows[k].component_id == root[k] and rows[k].kept == (root[k] == k)
        assert rows[k].n_links == sum(k in e for e in links)
    assert link_vectors(d.limit(0)).count() == 0


def test_tile_bounds_are_rigorous():
    rng = np.random.default_rng(1)
    x = unit(rng.normal(size=(300, 8)))
    side = (x, *quantise(x))
    q, s, e = quantise(x)
    approx = (q.astype(float) @ q.T.astype(float)) * s[:, None] * s[None, :]
    assert (np.abs(approx - x @ x.T) <= e[:, None] + e[None, :] + e[:, None] * e[None, :] + 1e-12).all()
    for t in (0.95, 0.3, -0.2):
        got = {(int(a), int(b)) for i, j in tile_links(side, None, t, 64) for a, b in zip(i, j)}
        assert got == {(a, b) for a in range(300) for b in range(a + 1, 300) if x[a] @ x[b] >= t}


@pytest.mark.parametrize("width", [1040, 1041, 3072])
def test_wide_vectors_are_compared(width):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(12, width))[rng.integers(0, 12, 60)] + rng.normal(size=(60, width)) * 0.22
    x = unit(np.concatenate([x, np.ones((2, width))]))
    got = {(int(a), int(b)) for i, j in tile_links((x, *quantise(x)), None, 0.95, 16) for a, b in zip(i, j)}
    assert got == {(a, b) for a in range(62) for b in range(a + 1, 62) if x[a] @ x[b] >= 0.95} and (60, 61) in got


URLS = ["https://Sub.Example.ORG/es/x?q", "http://example.org/en/123#a", "http://example.org/en/2", "https://a.com/fr/", "http://b.com/de/x", "http://b.com/DE/x", "no scheme", None, "", "http://org", "http://org/", "http://notorg/", "ftp://x.example.org:8/es/", "http://com/fr/#", "a://b.c.com/fr/?/de/", "http://xn.org\n/es/"]


def brute_url(url):
    if url is None or "://" not in url:
        return "", "", None, "allow"
    rest = url.split("://", 1)[1]
    cut = min([rest.find(c) for c in "?#" if c in rest], default=len(rest))
    rest = rest[:cut]
    k = rest.find("/")
    host, path = (rest, "") if k < 0 else (rest[:k], rest[k:])
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    hits = [(len(h + p), h + p, a) for h, p, a in RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return host, path, *(max(hits)[1:] if hits else (None, "allow"))


def test_urls(spark):
    rows = [(k, u, "x") for k, u in enumerate(URLS * 3)]
    d = spark.createDataFrame(rows, "page_id long, url string, path string").repartition(4)
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in judge_urls(d).collect()}
    assert got == {k: brute_url(u) for k, u, _ in rows}
    assert judge_urls(d.limit(0)).count() == 0
    table = spark.createDataFrame(RULES + [("deep.org", "/a", "block"), ("deep.org", "/a/b", "allow"), ("deep.org", "/a/b/c", "block")], "host string, path string, action string")
    more = spark.createDataFrame([(1, "http://z.deep.org/a/b/x"), (2, "http://deep.org/a/b/c/d"), (3, "http://deep.org/ab"), (4, "http://deep.org/b")], "page_id long, url string")
    assert {r.page_id: (r.rule, r.verdict) for r in judge_urls(more, table).collect()} == {1: ("deep.org/a/b", "allow"), 2: ("deep.org/a/b/c", "block"), 3: ("deep.org/a", "block"), 4: ("org/", "allow")}
    assert PathRules([("/", "h", "a")]).longest("") is None


@pytest.fixture(scope="module")
def vocabulary():
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


PARTS = ["a", "b", " ", " ", "\n", "\t", "\xa0", "é", "12", "'s", "<|endoftext|>", "!!", "\r", "\x00", "\x1c", "\x85", "日", "don't", ",", "ß.", "\u2003", " x", "\nEin", ".\n", "À", "\x7f", "ǅ"]


def encodes_whole(e):
    import pyarrow as pa

    texts = ["".join(rnd.choice(PARTS) for _ in range(rnd.randint(0, 14))) for _ in range(6000)] + ["", LONG]
    want = [x.ids for x in e.t.encode_batch(texts, add_special_tokens=False)] + [[]]
    for step in (len(texts), 1000):
        for k in range(0, len(texts), step):
            some = pa.array([*texts, None]).slice(k, step + (k + step >= len(texts)))
            ids, sizes = e.encode(some)
            assert [x.tolist() for x in np.split(ids, np.cumsum(sizes)[:-1])] == want[k : k + len(some)]


def test_pieces_encode_as_whole_texts(vocabulary):
    e = Encoder(vocabulary)
    assert e.by_pieces
    encodes_whole(e)
    encodes_whole(Encoder(vocabulary, most=100))


@pytest.mark.parametrize("how", ["words", "no pattern", "prefix", "lower"])
def test_other_vocabularies_encode_whole_texts(vocabulary, tmp_path, how):
    import json

    import public_tokenizers

    spec = json.load(open(vocabulary))
    if how == "no pattern":  # tokens may cross blanks
        spec["pre_tokenizer"]["use_regex"] = False
    elif how == "prefix":
        spec["pre_tokenizer"]["add_prefix_space"] = True
    else:
        spec["normalizer"] = {"type": "Lowercase"}
    at = tmp_path / "vocabulary.json"
    at.write_text(json.dumps(spec))
    e = Encoder(public_tokenizers.path("word_bpe_49k.json") if how == "words" else str(at))
    assert not e.by_pieces
    encodes_whole(e)


def test_a_vocabulary_without_some_bytes(vocabulary, tmp_path):
    import json

    spec = json.load(open(vocabulary))
    gone = {t for t in spec["model"]["vocab"] if "x" in t}
    spec["model"]["vocab"] = {t: i for t, i in spec["model"]["vocab"].items() if t not in gone}
    spec["model"]["merges"] = [m for m in spec["model"]["merges"] if "x" not in "".join(m)]
    at = tmp_path / "vocabulary.json"
    at.write_text(json.dumps(spec))
    encodes_whole(Encoder(str(at)))


def test_slices_by_bytes():
    import pyarrow as pa

    from vecboost.llm.tokens import by_bytes

    texts = [None, "", "abc", "x" * 50, "ab", None, "cd", "y" * 9, "z"]
    b = pa.RecordBatch.from_pydict({"text": texts})
    got = [s.column("text").to_pylist() for s in by_bytes(b, "text", 10)]
    assert sum(got, []) == texts and all(len(s) == 1 or sum(len(t or "") for t in s) <= 10 for s in got)


@pytest.mark.parametrize("bits", [False, True])
def test_planes_round_trip(bits):
    rows = [np.array([rnd.randint(0, 2**k - 1) for _ in range(n)], np.uint32) for k, n in [(3, 0), (16, 700), (32, 5), (20, 1024), (8, 1), (16, 0), (31, 3000)]]
    f = io.BytesIO()
    w = PlaneWriter(f, chunk=256, bits=bits)
    for k, r in enumerate(rows):
        w.add(None if k == 3 else k * 7 - 5, r)
    w.close()
    r = PlaneReader(f)
    assert [(i, x.tolist()) for i, x in r] == [(None if k == 3 else k * 7 - 5, x.tolist()) for k, x in enumerate(rows)]
    assert all(r.document(k).tolist() == x.tolist() for k, x in enumerate(rows))
    raw = bytearray(f.getvalue())
    raw[40] ^= 1
    with pytest.raises(Exception):
        list(PlaneReader(io.BytesIO(bytes(raw))))


def test_token_files(spark, docs, none, vocabulary):
    e = Encoder(vocabulary)
    got = sorted((r.start, r.doc_id, r.n_tokens, r.ids_crc32) for r in token_digests(docs, vocabulary).collect())
    start = 0
    texts = dict(enumerate(TEXTS)) | {None: "no id"}
    assert [g[1] for g in got] == sorted([*range(15), 5, None], key=lambda x: -1 if x is None else x)
    for s, i, n, crc in got:
        ids = np.array([*e.t.encode(texts[i] or "", add_special_tokens=False).ids, 0], "<u4")
        assert (s, n, crc) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += n
    assert token_digests(none, vocabulary).count() == 0


def test_buckets_are_optimal():
    from itertools import combinations

    for seed in range(20):
        r = random.Random(seed)
        lengths = sorted(r.sample(range(1, 60), 8))
        n, k = [r.randint(1, 9) for _ in lengths], r.randint(1, 4)
        t = [a * b - r.randint(0, 1) for a, b in zip(lengths, n)]
        bounds, waste = optimal_bounds(np.array(lengths), np.array(n), np.array(t), k)
        cost = lambda b: sum(next(x for x in b if x >= a) * c for a, c in zip(lengths, n)) - sum(t)  # noqa: B023, E731
        best = min(cost(sorted(c) + [lengths[-1]]) for j in range(k) for c in combinations(lengths[:-1], j))
        assert waste == best == cost(bounds) and len(bounds) <= k
    assert optimal_bounds(np.zeros(0), np.zeros(0), np.zeros(0), 3) == ([], 0)


def test_buckets_are_optimal_for_long_texts(spark):
    r = random.Random(3)
    sizes = [r.choice([r.randint(1, 40), r.randint(900, 1200), r.randint(5000, 90000)]) for _ in range(400)]
    lengths, n = np.unique(sizes, return_counts=True)
    tokens = lengths * n
    rows, toks = np.concatenate([[0], np.cumsum(n)]), np.concatenate([[0], np.cumsum(tokens)])
    best = np.array([0] + [10**15] * len(lengths))  # the program without a hull, bucket by bucket
    for _ in range(6):
        best = np.array([0] + [min(best[i] + lengths[j - 1] * (rows[j] - rows[i]) - (toks[j] - toks[i]) for i in range(j)) for j in range(1, len(lengths) + 1)])
    bounds, waste = optimal_bounds(lengths, n, tokens, 6)
    assert waste == best[-1] == sum(min(b for b in bounds if b >= s) - s for s in sizes) and len(bounds) <= 6
    d = spark.createDataFrame([(k, " ".join(["w"] * s)) for k, s in enumerate(sizes)], "doc_id long, text string").repartition(3)
    placed = pack(d, buckets=6).collect()
    assert sum(x.bucket_length - x.n_tokens for x in placed) == waste and {x.n_tokens for x in placed} == set(sizes)


def test_packing(docs, none):
    rows = pack(docs, budget=64, buckets=4).collect()
    assert len(rows) == 17 and len({r.bucket_length for r in rows}) <= 4
    texts = dict(enumerate(TEXTS)) | {None: "no id"}
    batches = {}
    for r in rows:
        assert r.n_tokens == max(1, len((texts[r.doc_id] or "").encode().split())) <= r.bucket_length
        batches.setdefault(r.batch, []).append(r)
    for b in batches.values():
        assert len({r.bucket_length for r in b}) == 1 and len(b) <= max(1, 64 // b[0].bucket_length) and sorted(r.place for r in b) == list(range(len(b)))
    for length in {r.bucket_length for r in rows}:  # all batches of a bucket but its last are full
        sizes = sorted(len(b) for b in batches.values() if b[0].bucket_length == length)
        assert sizes[1:] == [max(1, 64 // length)] * (len(sizes) - 1)
    assert pack(none).count() == 0


def test_budgets_go_to_siblings_before_ancestors():
    a = Node(0.5, children={"x": Node(0.5, 10), "y": Node(0.5, 1000)})
    b = Node(0.5, children={"z": Node(1.0, 1000)})
    root = Node(children={"a": a, "b": b})
    share(root, 400)
    assert [a.budget, b.budget, a.children["x"].budget, a.children["y"].budget] == [200, 200, 10, 190]
    share(root, 1900)
    assert a.budget == 950 and b.budget == 950 and a.children["x"].budget == 10
    share(root, 5000)
    assert root.budget == 2010 and a.budget + b.budget == 2010
    share(root, 7)
    assert a.budget + b.budget == 7


def test_mixing(spark, docs, none):
    rows = mix(docs, 0.5, epochs=3).collect()
    texts = dict(enumerate(TEXTS)) | {None: "no id"}
    size = lambda i: max(1, len((texts[i] or "").encode().split()))
    leaves = {}
    for r in rows:
        leaves.setdefault((r.lang, r.source), []).append(r)
    for rs in leaves.values():  # each leaf's picks are a gapless prefix
        at = 0
        for r in sorted(rs, key=lambda r: r.start):
            assert r.start == at and r.n_tokens == size(r.doc_id)
            at += r.n_tokens
    total = sum(map(size, [*range(15), 5, None]))
    assert total * 0.5 <= sum(r.n_tokens for r in rows) <= total * 0.5 + 3 * 6001
    out = take_mix(docs, 0.9)
    assert out.columns == docs.columns and out.count() <= 16
    assert mix(none).count() == 0


def test_mix_takes_the_prefix_of_each_seeded_epoch(spark):
    """Brute force: leaves by the weights two levels down, and in each epoch the seeded order's prefix."""
    r = random.Random(6)
    rows = [(k, " ".join(["w"] * r.randint(1, 30)), r.choice(["en", "de", None]), f"src{r.randint(0, 19)}") for k in range(300)]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").repartition(5)
    got = mix(d, 0.9, epochs=3, seed=5).collect()
    size = {i: len(t.split()) for i, t, _, _ in rows}
    domain = lambda s: "web" if int(s[3:]) <= 6 else "books" if int(s[3:]) <= 12 else "reference"
    leaves = {}
    for i, _, lang, s in rows:
        leaves.setdefault((domain(s), lang or "", s), []).append(i)
    stock = {k: sum(map(size.get, v)) for k, v in leaves.items()}
    target = round(0.9 * sum(stock.values()))
    plan = budgets([(*k, v) for k, v in stock.items()], target, 3, DOMAIN_WEIGHTS, LANGUAGE_WEIGHTS, {})
    assert sum(plan.values()) == target

    def within(prefix, of):
        return sum(v for k, v in of.items() if k[: len(prefix)] == prefix)

    top = {p[0] for p in plan}
    short = {p for p in top if within((p,), plan) == 3 * within((p,), stock)}
    rest = {p: within((p,), plan) / DOMAIN_WEIGHTS[p] for p in top - short}
    assert max(rest.values()) - min(rest.values()) < 20  # domains with stock enough are level by weight
    for p in rest:
        langs = {q[1] for q in plan if q[0] == p}
        level = {q: within((p, q), plan) / LANGUAGE_WEIGHTS.get(q, 1.0) for q in langs if within((p, q), plan) < 3 * within((p, q), stock)}
        assert max(level.values()) - min(level.values()) < 60
    hashed = {(x.doc_id, x.e): x.h for x in d.select("doc_id", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("e")).select("doc_id", "e", F.xxhash64("doc_id", F.lit(5), "e").alias("h")).collect()}
    want = []
    for leaf, ids in leaves.items():
        at = 0
        for e in range(3):
            for i in sorted(ids, key=lambda i: (hashed[i, e], i)):
                if at < plan[leaf]:
                    want.append((i, *leaf, size[i], e, at))
                at += size[i]
    assert sorted(tuple(x) for x in got) == sorted(want)


def test_take_mix_keeps_clashing_columns_and_rows_without_an_id(spark):
    rows = [(k if k % 7 else None, "a b c", "en", "src1", k, -k, "x") for k in range(40)] + [(3, "a b c", "en", "src1", 99, 0, "y")]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, _last int, _again int, _key string")
    out = take_mix(d, 1.0)
    assert out.columns == d.columns and sorted(map(str, out.collect())) == sorted(map(str, d.collect()))
    half = take_mix(d, 0.5).collect()
    assert 0 < len(half) < 41 and sum(r.doc_id is None for r in half) in (0, 6)
    assert take_mix(d.limit(0)).columns == d.columns and take_mix(d.limit(0)).count() == 0


def test_deobfuscation_and_scores(spark, docs, none):
    clean = [" ".join(rnd.choice(WORDS[:-2]) for _ in range(30)) for _ in range(300)]
    toxic = [c + " you idiot moron" for c in clean[:100]]
    rows = [(k, t) for k, t in enumerate(clean + toxic)]
    d = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    labels = spark.createDataFrame([(k, int(k >= 300)) for k in range(400)], "doc_id long, toxic int")
    model = toxicity.fit(d, labels)
    cost = model.cost.tolist()
    for said, meant in [("1d10t", "idiot"), ("i d i o t", "idiot"), ("m0r0n", "moron"), ("idiooooot", "idiot"), ("m.o.r.o.n", "moron"), ("1D10T!!", "idiot")]:
        assert meant in toxicity.restore(said, cost).lower(), said
        assert model.scorer()(f"the river {said} of stone moron idiot".encode()) > 0.5
    assert toxicity.restore("the river of 7 stones, 12.5 green", cost) == "the river of 7 stones, 12.5 green"
    got = {r.doc_id: r for r in toxicity.score_toxicity(d, labels, model=model).collect()}
    assert all(got[k].predicted == int(k >= 300) for k in range(400))
    assert all(got[k].held_out == (zlib.crc32(str(k).encode()) % 5 == 0) for k in range(400))
    odd = toxicity.score_toxicity(docs, labels, model=model).collect()
    assert len(odd) == 17 and all(0 <= r.score <= 1 for r in odd)
    assert toxicity.score_toxicity(none, labels).count() == 0
    assert toxicity.drop_toxic(d, labels, model=model).count() == 300
    counts = toxicity.gram_counts(d)
    want = toxicity.class_codes(b"\n" + b"\n\n".join(t.encode() for _, t in rows) + b"\n")
    assert abs(counts.sum() - len(want)) < 20


SPACED_OUT = ["s c u m,", "h a t e?", "s c u m!", '"m o r o n"', "(i d i o t)", "i. d. i. o. t", "i  d  i  o  t", "m- o- r- o- n", "x_i.d.i.o.t"]


def test_scores_read_what_restore_reads(monkeypatch):
    seen = []
    monkeypatch.setattr(toxicity, "decode", lambda s, cost: seen.append(s.lower()) or "word")
    r = random.Random(3)
    noise = ["".join(r.choice("ab1! ._-'é\n") for _ in range(r.randint(0, 24))) for _ in range(3000)]
    for text in [*SPACED_OUT, *("the river " + t + " of stone" for t in SPACED_OUT), "1d10t 'm0r0n', i d i o t", *noise]:
        assert toxicity.may_be_spaced(text.encode()) or not toxicity.SPACED.search(text)
        toxicity.restore(text, [])
        shown, seen[:] = {s.strip("'") for s in seen}, []
        toxicity.Reader(np.zeros(0)).features(text.encode())
        scored, seen[:] = {s.strip("'") for s in seen}, []
        assert scored == shown and (scored or text not in SPACED_OUT), text


def language(words, times=300):
    text = b"\n" + " ".join(rnd.choice(words) for _ in range(times * len(words))).encode() + b"\n"
    return toxicity.language_model(np.bincount(toxicity.class_codes(text), minlength=toxicity.CLASSES**4).astype(float)).tolist()


def test_doubled_signs_at_the_ends_are_read():
    cost = language([*WORDS, "kill", "ass", "dumbass", "great"])
    reader = toxicity.Reader(np.array(cost))
    for said, meant in [("ki11", "kill"), ("a$$", "ass"), ("a55", "ass"), ("dumba55", "dumbass"), ("Dumb4$$!!", "dumbass"), ("1d10t!!", "idiot")]:
        assert meant + "$" in reader.features(f"the {said} of stone".encode()), said
        assert meant in toxicity.restore(f"the {said}, of stone", cost).split(",")[0], said
    assert toxicity.restore("The Great!! river of stone! **Great**", cost) == "The Great!! river of stone! **Great**"
    for s, want in [("ab!!*", "ab"), ("ab*!!", "ab"), ("ab$$!!", "ab$$"), ("a$$", "a"), ("++ab", "ab"), ("*+ab1", "ab1"), ("11", "11"), ("111", "")]:
        assert toxicity.bare(s) == want


def test_long_segments_and_doubled_letters_are_read():
    cost = language([*WORDS, "stupid", "letter", "all", "room"])
    reader = toxicity.Reader(np.array(cost))
    for said, meant in [("m" + "0" * 70 + "ron", "moron"), ("id1" + "i" * 70 + "ot", "idiot"), ("m0r0n" * 40 + "id10t", "idiot"), ("iddiot", "idiot"), ("mooron", "moron"), ("stuupid", "stupid"), ("Stup1dd", "stupid"), ("IddiOt", "idiot")]:
        assert any(f.startswith(meant[:4]) for f in reader.features(f"the {said} of stone".encode())) or len(said) > 80, said
        assert toxicity.restore(f"the {said} of stone", cost).endswith(f"{meant} of stone"), said
    assert toxicity.restore("All the Green letters under a room", cost).split()[:3] == ["All", "the", "Green"]
    assert "letter" in toxicity.restore("a letter", cost) and toxicity.restore("room", cost) == "room"
    assert len(toxicity.decode("m0r0n1" * 20_000, cost)) > 100_000  # in steps, not in their square


def test_segments_that_cannot_matter_are_those_without_wanted_readings():
    r = random.Random(5)
    cost = toxicity.language_model(np.bincount(toxicity.class_codes(b"kill idiot moron a book of all fools " * 50), minlength=toxicity.CLASSES**toxicity.ORDER).astype(float))
    wanted = {"kil$", "idiot$", "idio", "ass$", "moron", "a$", "fool$"}
    told, all_ = toxicity.Reader(cost, wanted), toxicity.Reader(cost)
    words = ["".join(c * r.choice([1, 1, 2, 3]) for c in r.choice(["kil", "idiot", "as", "moron", "a", "fol", "book", "idol", "xyz"])) for _ in range(400)]
    for w in words:
        assert set(told.of_token(w)) == set(all_.of_token(w)) & wanted
    assert sum(not told.may_matter(w) for w in words) > 50


def test_viterbi_is_the_cheapest_path():
    from itertools import product

    rng = np.random.default_rng(0)
    cost = rng.random(toxicity.CLASSES**4) * 5

    def price(said):
        x = [0, 0, 0]
        total = 0.0
        for d in [*said, 0]:
            if d or x[-1]:
                total += cost[((x[-3] * 28 + x[-2]) * 28 + x[-1]) * 28 + d]
                x.append(d)
        return total

    for s in ("1d10t", "a$$b", "s0o0n"):
        paths = product(*toxicity.lattice(s))
        best = min(paths, key=lambda p: price([c for out, _ in p for c in out]) + sum(w for _, w in p))
        text = "".join(" " if c == 0 else chr(96 + c) for out, _ in best for c in out)
        assert " ".join(toxicity.decode(s, cost.tolist()).split()) == " ".join(text.split())


def test_warc(spark, tmp_path):
    big = "é" * 600
    pages = [(1, "http://a/ b\r\nX: y", big), (2, "u", big), (3, None, None), (4, "v", "x" * 999), (5, "v", "x" * 999), (6, "w", big), (6, "w", big), (7, "z", "\r\n\r\nWARC/1.1\r\nContent-Length: 5\r\n\r\n" * 40), (8, "z", "y" * 300_000)]
    d = spark.createDataFrame([(*p, "clash") for p in pages], "page_id long, url string, html string, digest string").repartition(3)
    got = sorted((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to or 0) for r in archive_digest(d, f"file://{tmp_path}/w").collect())
    want = []
    for i, _, h in pages:
        b = (h or "").encode()
        same = [j for j, _, g in pages if (g or "").encode() == b]
        again = len(b) >= 1000 and i != max(same)
        want.append((i, len(b), hashlib.sha1(b).hexdigest(), "revisit" if again else "response", max(same) if again else 0))
    assert got == sorted(want)
    files = archive_pages(d, f"file://{tmp_path}/x")
    back = {r.page_id: r for r in read_archives(files).collect()}
    assert back[8].payload == b"y" * 300_000 and back[1].url == "http://a/ b\r\nX: y" and back[2].payload is None
    assert archive_digest(d.limit(0)).count() == 0


def brute_passages(rows, size=50):
    least = {}
    for i, t in sorted(rows, key=lambda r: r[0]):
        for k in range(len(t) - size + 1):
            least.setdefault(t[k : k + size], i)
    out = []
    for i, t in rows:
        gone = bytearray(len(t))
        for k in range(len(t) - size + 1):
            if least[t[k : k + size]] < i:
                gone[k : k + size] = b"\1" * size
        spans = sum(bool(gone[k]) and (k == 0 or not gone[k - 1]) for k in range(len(gone)))
        out.append((i, len(t), sum(gone), spans, hashlib.sha256(bytes(c for c, g in zip(t, gone) if not g)).hexdigest()))
    return sorted(out)


def test_suffix_order():
    for trial in range(30):
        r = random.Random(trial)
        t = np.array([r.choice(b"ab" if trial % 2 else b"abc\xff\0") for _ in range(r.choice([1, 2, 9, 300, 900]))], np.uint8)
        t = np.tile(t, 1 + trial % 3)
        k = [t.tobytes()[i : i + 50] for i in suffix_order(t)]
        assert sorted(suffix_order(t).tolist()) == list(range(len(t))) and k == sorted(k)


def test_passages(spark, docs, none):
    texts = dict(enumerate(TEXTS)) | {2**63 - 1: "no id"}
    rows = [(i, (t or "").encode()) for i, t in texts.items()] + [(5, COPY.encode())]
    got = sorted((2**63 - 1 if r.doc_id is None else r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in passage_digests(docs).collect())
    assert got == brute_passages(rows)
    r = random.Random(9)
    pool = ["".join(r.choice("ab cé") for _ in range(r.randint(40, 130))) for _ in range(7)]
    many = [(k, "".join(r.choice(pool)[r.randint(0, 25) :] if r.random() < 0.6 else "z" * r.randint(0, 80) for _ in range(r.randint(0, 6)))) for k in range(90)]
    d = spark.createDataFrame(many, "doc_id long, text string").repartition(6)
    got = sorted(tuple(r) for r in passage_digests(d).collect())
    assert got == brute_passages([(i, t.encode()) for i, t in many])
    cut = {r.doc_id: r.text for r in cut_passages(docs).collect()}
    assert cut[8] == LONG and cut[9] == " tail"[-len(cut[9]) :] and cut[6] == ""
    assert cut_passages(docs).columns == docs.columns and cut_passages(docs).count() == 17
    assert passage_digests(none).count() == 0


@pytest.mark.parametrize("often", [2, 10**9])
def test_an_anchor_in_many_different_stretches(spark, monkeypatch, often):
    """One frequent string, whose middle has the least hash of its surroundings, between ever other neighbours."""
    r = random.Random(12)
    gram = min(("".join(r.choice("abcdefgh") for _ in range(24)) for _ in range(30000)), key=lambda g: anchors((g + "x" * 26).encode(), np.array([50]))[0][0])
    monkeypatch.setattr(suffix_dedup, "OFTEN", often)
    monkeypatch.setattr(suffix_dedup, "ARRAY", 4000)
    sides = ["".join(r.choice("ijkl") for _ in range(40)) for _ in range(12)]
    texts = [r.choice(sides)[r.randint(0, 30) :] + r.choice(["", "q", "rs"]) + gram + r.choice(["", "t"]) + r.choice(sides)[: r.randint(5, 40)] + str(k) for k in range(500)]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    got = sorted(tuple(x) for x in passage_digests(d).collect())
    assert got == brute_passages([(k, t.encode()) for k, t in enumerate(texts)]) and sum(g[2] > 0 for g in got) > 100


def test_a_long_text_is_read_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "BLOCK", 120)
    r = random.Random(13)
    pool = ["".join(r.choice("abcdé ") for _ in range(90)) for _ in range(5)]
    texts = ["".join(r.choice(pool)[r.randint(0, 30) :] for _ in range(r.choice([1, 2, 12]))) for _ in range(40)]
    got = sorted(tuple(x) for x in passage_digests(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)).collect())
    assert got == brute_passages([(k, t.encode()) for k, t in enumerate(texts)])


def test_pipeline_stages_take_any_table(spark, sf, docs, none):
    """Nulls in every column, repeated rows, empty and long texts, ties, clashing names and no rows at all."""
    import corpus_pipeline as P

    for d in (docs.withColumn("_last", F.lit(1)).withColumn("root", F.lit("x")).withColumn("_id", F.lit(None).cast("string")).withColumn("digest", F.lit("y")), none):
        for name, stage in P.STAGES:
            out = stage(spark, d, sf)
            if name != "packing":
                assert out.columns == d.columns
            rows = out.collect()
            assert len(rows) <= d.count() and (rows or d.isEmpty())
            if name in ("passages", "packing"):
                assert len(rows) == d.count()


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in P.STAGES] == ["toxicity", "near_duplicates", "passages", "mixture", "packing"]
    d = docs
    for name, stage in P.STAGES:
        before = {r.doc_id: r.text for r in d.collect()}
        out = stage(spark, d, sf).persist()
        ids = [r.doc_id for r in out.collect()]
        assert len(ids) == len(set(ids)) and set(ids) <= set(before)
        if name != "packing":
            assert out.columns == docs.columns
        if name == "near_duplicates":
            words = {i: (t or "").lower().encode().split() for i, t in before.items()}
            sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set() for i, w in words.items()}
            close = [(a, b) for a in sets for b in sets if a < b and (sets[a] == sets[b] or 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]))]
            assert set(ids) == set(union_find(sets, close).values())
        if name == "passages":
            assert len(ids) == len(before) and all(len(r.text) <= len(before[r.doc_id]) for r in out.collect())
        if name == "packing":
            assert len(ids) == len(before)
        d = out
    assert P.run(spark, sf).count() == len(ids)


def test_held_out_accuracy(spark, sf):
    sf1 = sf.replace("0.001", "0.01")
    docs, labels = spark.read.parquet(f"{sf1}/documents.parquet"), spark.read.parquet(f"{sf1}/labels.parquet")
    s = toxicity.score_toxicity(docs, labels).join(labels, "doc_id").where("held_out")
    assert s.agg(F.avg((F.col("predicted") == F.col("toxic")).cast("double"))).first()[0] > 0.9
    q = quality.judge_quality(docs, labels).join(labels, "doc_id").where("not base_failed")
    assert q.agg(F.avg((F.col("kept") == (F.col("quality") == 1)).cast("double"))).first()[0] > 0.95
