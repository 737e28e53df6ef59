"""Each text operator against brute force, and on nulls, empty and long texts, ties, repeated rows, no rows and clashing columns."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
import tiktoken
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from linseg.llm import bm25, bpe, classlm, graph, licences, mixing, neardup, quality, simhash, tokencounts, tokenfile, toxicity
from linseg.llm.common import load
from linseg.llm.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
EDGE = [
    (1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "two words"), (5, "two words"), (6, "same id"), (6, "other text"), (None, "no id"), (None, None),
    (7, "ÀÉ ß 　 x\x00y 😀😀"), (8, "long " * 30_000), (9, "x" * 20_000), (10, "a b c d e f g h i j k l.\na b c d e f g h i j k l."), (-3, "negative"),
]


@pytest.fixture(scope="module")
def edge(spark):
    """With columns whose names the operators use inside."""
    rows = [(i, t, "en", None if i == 4 else "s", 0, 1.0, "w", False) for i, t in EDGE]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score double, word string, kept boolean")


@pytest.fixture(scope="module")
def none(edge):
    return edge.where("1 = 0")


@pytest.fixture(scope="module")
def docs(spark):
    return load(spark, SF, "documents")


@pytest.fixture(scope="module")
def labels(spark):
    return load(spark, SF, "labels")


def rows(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)


# 1 Byte-level BPE


@pytest.fixture(scope="module")
def tik():
    import base64

    file, pattern = bpe.default_vocabulary()
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(file, "rb"))}
    return tiktoken.Encoding("t", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def test_bpe_is_the_library(docs, edge, none, tik):
    for df in (docs, edge):
        want = []
        for r in df.collect():
            ids = tik.encode_ordinary(r.text or "")
            want.append((r.doc_id, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest()))
        got = bpe.encode(df, *bpe.default_vocabulary())
        assert rows(got, "doc_id", "n_tokens", "ids_sha256", "decoded_sha256") == sorted(want, key=repr)
        back = bpe.decode(got, *bpe.default_vocabulary())
        assert Counter((r.doc_id, bytes(r.decoded)) for r in back.collect()) == Counter((r.doc_id, (r.text or "").encode()) for r in df.collect())
    assert bpe.encode(none, *bpe.default_vocabulary()).count() == 0


def test_bpe_on_hard_texts(tik):
    c = bpe.Codec(*bpe.default_vocabulary(), cache=20_000)
    rng = random.Random(0)
    texts = ["", " ", "a  b", "a \n\n b ", "a\n ", "a\x1cb \x1c c", "it's we'll  'S", "a" * 3000, "ab" * 900, "é" * 300 + "zq" * 50]
    texts += ["".join(rng.choice("abcdeth") for _ in range(600)), *["".join(rng.choice(" \n\t ab.'1　é") for _ in range(30)) for _ in range(400)]]
    texts += ["".join(rng.choice(a) for _ in range(rng.randrange(161, 900))) for a in ("etaoinshrdlu", "ab", "acgt", "étaoübв語漢") for _ in range(60)]
    for lo in range(0, len(texts), 100):
        ids, back = c.encode(texts[lo : lo + 100])
        assert ids.to_pylist() == [tik.encode_ordinary(t) for t in texts[lo : lo + 100]]
        assert back.to_pylist() == [t.encode() for t in texts[lo : lo + 100]]


@pytest.mark.parametrize("letters", ["abcdefghijklmnopqrstuvwxyz", "ab", "x"])
def test_bpe_long_word_in_few_steps(tik, letters):
    import time

    c = bpe.Codec(*bpe.default_vocabulary())
    text = "".join(random.Random(3).choice(letters) for _ in range(60_000))
    began = time.process_time()
    (ids,), _ = c.encode([text])
    assert ids.as_py() == tik.encode_ordinary(text) and time.process_time() - began < 20


# 2 Mixing


def test_mixing_reaches_its_marginals(docs, spark):
    target = {"source": {f"src{i}": 1 / 20 for i in range(20)}}
    got = mixing.mix(docs, target, budget=0.2)
    cells = got.groupBy("source").agg({"n_tokens": "sum"}).collect()
    m = mixing.achieved(got).where("dimension = 'source'").collect()
    total = sum(r.tokens for r in m)
    assert len(cells) == 20
    for r in m:
        assert r.expected == pytest.approx(min(r.tokens, 0.2 * total / 20), rel=1e-3)


def test_mixing_table_form_is_the_driver_form(docs):
    small = docs.where("source in ('src0', 'src1', 'src2')")
    d = mixing.described(small)
    a = {tuple(r)[:3]: r.probability for r in mixing.probabilities(d, rounds=6).collect()}
    b = {tuple(r)[:3]: r.probability for r in mixing.probabilities(d, rounds=6, driver_cells=0).collect()}
    assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k]) for k in a)


def test_mixing_edges(edge, none):
    got = mixing.mix(edge).collect()
    assert len(got) == len(EDGE) and all(0 <= r.probability <= 1 for r in got)
    assert len({r.kept for r in got if r.doc_id == 5}) == 1
    assert mixing.mix(none).count() == 0 and mixing.sample(none).columns == edge.columns
    assert mixing.sample(edge).columns == edge.columns
    odd = edge.selectExpr("*", "doc_id + 1 as __p", "text as __mix", "'x' as `__KEPT`", "1 as __cell")
    kept = {r.doc_id for r in got if r.kept}
    assert all(r["__mix"] == r.text and r["__p"] == (None if r.doc_id is None else r.doc_id + 1) and r.doc_id in kept for r in mixing.sample(odd).collect())
    other = edge.selectExpr("doc_id as i", "text as t", "source as s", "lang as l")
    assert rows(mixing.mix(other, id_col="i", text_col="t", source="s", lang="l"), "doc_id", "kept", "probability") == rows(mixing.mix(edge), "doc_id", "kept", "probability")


def test_mixing_hands_on_what_a_name_cannot_give():
    tokens = np.array([10.0, 500.0, 400.0, 90.0])
    codes = [np.array([0, 1, 2, 2]), np.array([0, 0, 1, 1])]
    targets = [np.array([200.0, 200.0, 200.0]), np.array([300.0, 300.0])]
    assert mixing.reachable(targets[0], np.array([10.0, 500.0, 490.0])).tolist() == [10, 295, 295]
    m = mixing.rake(tokens, codes, targets, 0.6, 500)
    assert m.sum() == pytest.approx(600, rel=1e-6) and (m <= tokens + 1e-9).all() and mixing.residual(tokens, codes, targets, m) < 0.02


# 3 SimHash


def brute_fingerprint(text):
    w = (text or "").encode().translate(bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))).split()
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 3]), 42) for i in range(len(w) - 2)] or [xxhash.xxh64_intdigest(b" ".join(w), 42)]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_groups(fps, ids):
    p = list(range(len(fps)))

    def root(i):
        while p[i] != i:
            i = p[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 3:
                p[root(i)] = root(j)
    least: dict = {}
    for i, x in enumerate(ids):
        if x is not None:
            least[root(i)] = min(x, least.get(root(i), x))
    return [least.get(root(i)) for i in range(len(fps))]


@pytest.mark.parametrize("group", [1024, 2])
def test_simhash_groups(docs, edge, none, group):
    for df in (docs, edge):
        src = df.collect()
        fps = [brute_fingerprint(r.text) for r in src]
        want = sorted(zip([r.doc_id for r in src], fps, brute_groups(fps, [r.doc_id for r in src])), key=repr)
        got = sorted(((r.doc_id, r.fp % (1 << 64), r.component_id) for r in simhash.groups(df, group=group).collect()), key=repr)
        assert got == want
    assert simhash.groups(none).count() == 0


def test_every_pair_within_the_radius_meets():
    from itertools import combinations

    for masks, bits in ((simhash.MASKS, range(64)), (simhash.DEEPER[4], [i for i in range(64) if not simhash.MASKS[4] >> i & 1])):
        for three in combinations(bits, 3):
            assert any(not m & sum(1 << b for b in three) for m in masks)


def test_large_groups_keep_every_link(spark):
    """Thousands of fingerprints within a few bits of each other, dealt a second time."""
    rng = random.Random(4)
    base = rng.getrandbits(64)
    fps = {base} | {base ^ sum(1 << b for b in rng.sample(range(24), rng.randint(1, 3))) for _ in range(1500)} | {rng.getrandbits(64) for _ in range(300)}
    signed = [x - (1 << 64) if x >> 63 else x for x in fps]
    stars = graph.components(simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), 64)).collect()
    want = brute_groups(list(fps), signed)
    top = {r.a: r.b for r in stars}
    assert [top.get(x, x) for x in signed] == want


def test_components_over_many_tasks(spark):
    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(200)] + [(rng.randrange(1000, 1500), rng.randrange(1000, 1500)) for _ in range(250)]
    got = {r.a: r.b for r in graph.components(spark.createDataFrame(edges, "a long, b long"), per_task=60).collect()}
    p: dict = {}

    def root(x):
        p.setdefault(x, x)
        while p[x] != x:
            x = p[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        p[max(a, b)] = min(a, b)
    assert got == {x: root(x) for x in list(p) if root(x) != x}


def test_one_of_each_group_stays(docs, edge, none):
    found = {r.doc_id: r.component_id for r in simhash.groups(docs).collect()}
    assert sorted(r.doc_id for r in simhash.keep_one(docs).collect()) == sorted(set(found.values()))
    assert simhash.keep_one(edge).columns == edge.columns and simhash.keep_one(none).count() == 0


@pytest.mark.parametrize("operator", [simhash, neardup])
@pytest.mark.parametrize("turn", range(6))
def test_rows_that_share_an_id_keep_their_texts(spark, operator, turn):
    from itertools import permutations

    a, b = "one two three four five six seven", "eight nine ten eleven twelve thirteen"
    rows_ = list(list(permutations([(3, b), (5, b), (5, a)]))[turn]) + [(None, a), (None, "none of them has an id at all"), (None, "none of them has an id at all")]
    got = sorted(map(tuple, operator.keep_one(spark.createDataFrame(rows_, "doc_id long, text string")).collect()), key=repr)
    assert got == sorted([(3, b), (5, a), (None, "none of them has an id at all")], key=repr)


# 4 BM25 (the whole query is compared with SQL below)


def test_search_with_small_shards_is_the_same(docs, none, edge, monkeypatch, tmp_path):
    want = rows(bm25.search(docs, docs.where("doc_id % 20 = 0"), 5), "query_id", "rank", "doc_id", "score")
    texts = {r.doc_id: Counter((r.text or "").encode().translate(bm25.LOWER).split()) for r in docs.collect()}
    n, avg = len(texts), sum(sum(b.values()) for b in texts.values()) / len(texts)
    df = Counter(t for b in texts.values() for t in b)
    brute = []
    for q in (i for i in texts if i % 20 == 0):
        s = {}
        for d, bag in texts.items():
            dl = sum(bag.values())
            v = sum(c * math.log(1 + (n - df[t] + 0.5) / (df[t] + 0.5)) * bag[t] * 2.2 / (bag[t] + 1.2 * (0.25 + 0.75 * dl / avg)) for t, c in texts[q].items() if t in bag)
            if v:
                s[d] = round(v, 6)
        brute += [(q, i + 1, d, x) for i, (d, x) in enumerate(sorted(s.items(), key=lambda y: (-y[1], y[0]))[:5])]
    assert [w[:3] for w in want] == [b[:3] for b in sorted(brute, key=repr)]
    assert bm25.search(none, none).count() == 0 and bm25.search(docs, none).count() == 0
    got = bm25.search(edge, edge.where("doc_id in (1, 4, 5)"), 3).collect()
    assert {r.query_id for r in got} == {4, 5} and [r.doc_id for r in got if r.query_id == 4][0] == 4


def test_pruning_changes_nothing():
    rng = random.Random(2)
    bags = [Counter(rng.choice(b"abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(1, 60))) for _ in range(700)]
    p = bm25._Postings()
    for i, b in enumerate(bags):
        p.add(i, b" ".join(bytes([t]) for t in b.elements()))
    s = bm25.Shard(p.dump(), 30.0)
    for k in (1, 10):
        q = [b"a", b"q", b"z", b"!"]
        w = [3.0, 1.0, 0.2, 9.0]
        full = {d: x for d, x in s.search(q, w, 700)}
        top = sorted(full.items(), key=lambda y: (-y[1], y[0]))[:k]
        assert sorted(s.search(q, w, k), key=lambda y: (-y[1], y[0]))[:k] == top


# 5 Licences (the whole query is compared with SQL below)


def test_licence_texts_in_disguise(spark, none):
    mit = licences.LICENCES["MIT"]
    other = "Copyright 2020 Somebody\n\n" + mit.upper().replace("LICENSE", "LICENCE").replace(",", " ;") + "\n  (c) 2021 Another One. All rights reserved.\n"
    df = spark.createDataFrame([(1, mit), (2, other), (3, mit + " more"), (4, None), (5, ""), (6, "x\nreleased under the mit licence\ny"), (6, "x\nreleased under the mit licence\ny")], "doc_id long, text string")
    got = sorted(licences.scan(df).collect(), key=lambda r: r.doc_id)
    assert [r.license for r in got] == ["MIT", "MIT", None, None, None, None, None]
    assert [r.n_notices for r in got] == [0, 0, 0, 0, 0, 1, 1] and got[-1].notices == "MIT"
    assert licences.scan(none).count() == 0


def test_every_licence_is_found_and_edges_are_not(spark, edge):
    texts = [(i, n, t) for i, (t, n) in enumerate(licences.with_untitled(licences.LICENCES).items())]
    planted = spark.createDataFrame([(i, "(c) 2001 A\n" + t.replace(" ", "  ").lower()) for i, _, t in texts], "doc_id long, text string")
    assert {r.doc_id: r.license for r in licences.scan(planted).collect()} == {i: n for i, n, _ in texts}
    got = licences.scan(edge.withColumn("name", F.lit("x")).withColumn("known_digest", F.lit("y"))).collect()  # long texts, clashing names, repeated rows
    assert len(got) == len(EDGE) and not any(r.license or r.n_notices for r in got)


# 6 Quality


def brute_base(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    grams = Counter(tuple(words[i : i + 5]) for i in range(len(words) - 4))
    inside = {i + j for i in range(len(words) - 4) if grams[tuple(words[i : i + 5])] > 1 for j in range(5)}
    seen, again = set(), 0
    for line in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            again += line in seen
            seen.add(line)
    n = len(words)
    return n, sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), again, len(inside), n < 10 or 100 * len(inside) > 20 * n


def test_quality_counts_and_verdicts(docs, labels, edge, none):
    field = quality.fit(docs, labels)
    for df in (docs, edge):
        got = quality.assess(df, field)
        want = sorted(((r.doc_id, *brute_base(r.text)) for r in df.collect()), key=repr)
        assert rows(got, "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed") == want
        assert quality.keep_good(df, field).count() == got.where("kept").count() and quality.keep_good(df, field).columns == df.columns
        assert got.where("kept and base_failed").count() == 0
    j = quality.assess(docs, field).join(labels, "doc_id").where("not base_failed")
    assert j.where("quality = 1 and not kept").count() <= 0.02 * j.where("quality = 1").count() and j.where("quality = 0 and kept").count() <= 0.2 * max(1, j.where("quality = 0").count()) + 1
    assert quality.assess(none, field).count() == 0
    assert quality.fit(none, labels) is None and quality.fit(docs, labels.where("quality = 1")) is None
    assert quality.assess(edge, None).where("kept = base_failed").count() == 0


def test_verdicts_by_a_plain_decoder(docs, labels, edge):
    field = quality.fit(docs, labels)
    for df in (docs, edge):
        got = sorted(((r.doc_id is None, r.doc_id or 0, r.content_share, r.kept) for r in quality.assess(df, field).collect()))
        want = []
        for r in df.collect():
            lines, seen, rows_, sizes = (r.text or "").encode().split(b"\n"), set(), [], []
            for line in lines:
                if own := line.split():
                    rows_.append(quality.line_features(line, own, line in seen))
                    seen.add(line)
                    sizes.append(len(own))
            paths = {0: (0.0, []), 1: (0.0, [])}
            for i, f in enumerate(rows_):
                e = float(np.dot(f, field.weights))
                step = {}
                for y in (0, 1):
                    before = max((paths[p][0] + (field.moves[p][y] if i else 0.0), -p) for p in (0, 1)) if i else (0.0, -y)
                    step[y] = (before[0] + e * y, [*(paths[-before[1]][1] if i else []), y])
                paths = step
            best = paths[1] if paths[1][0] > paths[0][0] else paths[0]
            share = sum(n for n, y in zip(sizes, best[1]) if not y) / sum(sizes) if sizes else 0.0
            want.append((r.doc_id is None, r.doc_id or 0, share, not brute_base(r.text)[-1] and share >= field.threshold))
        for a, b in zip(got, sorted(want), strict=True):
            assert a[:2] == b[:2] and a[2] == pytest.approx(b[2]) and a[3] == b[3]


def test_viterbi_is_the_best_path():
    from itertools import product

    rng = np.random.default_rng(0)
    for _ in range(30):
        f = quality.Field(rng.normal(size=3).tolist(), rng.normal(size=(2, 2)).tolist(), 0.5)
        x = rng.normal(size=(6, 3))
        e = x @ f.weights
        score = lambda y: sum(e[i] for i in range(6) if y[i]) + sum(f.moves[a][b] for a, b in zip(y, y[1:]))
        assert score(f.decode(x).tolist()) == pytest.approx(max(map(score, product((0, 1), repeat=6))))


def test_field_gradient_learns_chains():
    rng = np.random.default_rng(1)
    x, y = [], []
    for _ in range(60):
        lab = np.repeat(rng.integers(0, 2, 4), 5)
        x.append(np.column_stack([np.ones(20), lab + rng.normal(0, 0.6, 20)]))
        y.append(lab)
    w, move = quality._likelihood(x, y)
    f = quality.Field(w.tolist(), move.tolist(), 0.5)
    assert np.mean([np.mean(f.decode(a) == b) for a, b in zip(x, y)]) > 0.85 and move[0, 0] > move[0, 1] and move[1, 1] > move[1, 0]


# 7 Class-based scores


@pytest.mark.parametrize("sizes", [{}, {"head": 50, "common": 300, "classes": 8}, {"head": 50, "common": 3000, "classes": 8, "clustered": 1000}])
def test_class_scores(docs, edge, none, sizes):
    for df in (docs, edge):
        src = df.collect()
        tok = [(r.text or "").encode().translate(classlm.LOWER).split() for r in src]
        out = [zlib.crc32(b"" if r.doc_id is None else str(r.doc_id).encode()) % 7 == 2 for r in src]
        c: Counter = Counter()
        for t, o in zip(tok, out, strict=True):
            if not o:
                c.update(t)
                c[None] += 1
        n, v = sum(c.values()), len(c)
        want = sorted(((r.doc_id, o, len(t) + 1, sum(c[w] > 0 for w in [*t, None]), n, round(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in [*t, None]), 4)) for r, t, o in zip(src, tok, out, strict=True)), key=repr)
        got = classlm.score(df, **sizes).collect()
        assert sorted(((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 4)) for r in got), key=repr) == want
        train = df.where(~classlm.held_out(F.col("doc_id"))).select("text")
        m = classlm.fit(train, classlm.word_counts(train), **sizes)
        sized = len(m.emit) if not sizes else min(sizes.get("clustered", classlm.CLUSTERED), len(m.emit))
        by_id = lambda x: (x[0] is None, x[0] or 0, x[1])
        brute = sorted(zip([r.doc_id for r in src], brute_class_scores(tok, out, m, sized), strict=True), key=by_id)
        for a, b in zip(sorted(((r.doc_id, r.score) for r in got), key=by_id), brute, strict=True):
            assert a[0] == b[0] and a[1] == pytest.approx(b[1], rel=1e-9, abs=1e-6)
    assert classlm.score(none).count() == 0


def brute_class_scores(tok, out, m, clustered):
    """Log10 probabilities from the model's classes alone: bigrams, sizes and types counted anew."""
    in_class = {w: int(m.word_class[i]) for w, i in m.words.items() if i < clustered}
    shapes, end = int(m.shape_class[0]), m.end
    of = lambda w: in_class[w] if w in in_class else shapes + classlm.shape(w)
    pairs, before, after, words, types = Counter(), Counter(), Counter(), Counter(), Counter()
    for t, o in zip(tok, out, strict=True):
        if not o:
            words.update(t)
            path = [end, *map(of, t), end]
            pairs.update(zip(path, path[1:]))
    for (a, b), c in pairs.items():
        before[a] += c
        after[b] += c
    types.update(of(w) for w in words if w not in in_class)
    size = Counter()
    for w, c in words.items():
        size[of(w)] += c
    k, total = len(m.moves), sum(after.values())
    some = Counter(a for a, _ in pairs)

    def move(a, b):
        own = (after[b] + 1) / (total + k)
        return (max(pairs[a, b] - 0.7, 0) + 0.7 * some[a] * own) / before[a] if before[a] else own

    def emit(w):
        c = of(w)
        return words[w] / size[c] if w in in_class else (words[w] + 1) / (size[c] + types[c] + 1)

    return [sum(math.log10(move(a, b)) for a, b in zip([end, *map(of, t)], [*map(of, t), end])) + sum(math.log10(emit(w)) for w in t) for t in tok]


def test_class_model_adds_up():
    """Over all next tokens, unseen ones of each shape included, the probabilities sum to one."""
    rng = random.Random(0)
    words = [w.encode() for w in "the cat dog sat ran on a mat. big red the the".split()]
    texts = [[rng.choice(words) for _ in range(8)] for _ in range(40)]
    c = Counter(w for t in texts for w in t)
    common = sorted(c.items(), key=lambda x: (-x[1], x[0]))
    of = np.array([0, 1, 2, 0])
    size = 3 + classlm.SHAPES + 1
    place = {w: int(of[i]) for i, (w, _) in enumerate(common[:4])}
    table = np.zeros((size, size))
    for t in texts:
        at = [size - 1, *[place.get(w, 3 + classlm.shape(w)) for w in t], size - 1]
        for a, b in zip(at, at[1:]):
            table[a, b] += 1
    types = np.bincount([classlm.shape(w) for w, _ in common[4:]], minlength=classlm.SHAPES)
    m = classlm.Model(common, of, 3, table, types, 0, 0, 40)
    assert np.allclose((10**m.moves).sum(1), 1)
    by: Counter = Counter()
    for w, i in m.words.items():
        by[m.word_class[i]] += 10 ** m.emit[i]
    for s in range(classlm.SHAPES):
        by[m.shape_class[s]] += 10 ** -m.shape_base[s]
    assert all(v == pytest.approx(1) for v in by.values())


def test_exchange_only_raises_the_likelihood():
    rng = np.random.default_rng(3)
    table = rng.poisson(2, (23, 23)).astype(float)

    def likelihood(of):
        k = of.max() + 1
        m = np.eye(k)[of]
        g = m.T @ table @ m
        f = lambda x: (x * np.log(np.maximum(x, 1))).sum()
        return f(g) - f(g.sum(1)) - f(g.sum(0))

    runs = [likelihood(classlm.exchange(table, 20, 4, s)) for s in (0, 1, 3, 10)]
    assert all(a <= b + 1e-9 for a, b in zip(runs, runs[1:])) and runs[-1] > runs[0]


# 8 Token files


def test_token_files(docs, edge, none, spark, tmp_path):
    file = P.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(file)
    for k, df in enumerate((docs, edge)):
        folder = f"file://{tmp_path}/t{k}"
        order = sorted(((r.doc_id is not None, r.doc_id or 0, r.text is not None, r.text or "") for r in df.collect()))
        want, start, by = [], 0, {}
        for named, i, _, text in order:
            ids = [*tok.encode(text, add_special_tokens=False).ids, 2]
            want.append((i if named else None, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
            by.setdefault(i if named else None, []).append(ids)
            start += len(ids)
        m = tokenfile.write(df, file, folder)
        assert rows(tokenfile.read_back(m, folder), "doc_id", "start", "n_tokens", "ids_crc32") == sorted(want, key=repr)
        shards = [tokenfile.Shard(folder, r.shard) for r in m.collect()]
        for i in [x for x in by if x is not None]:
            assert [x.tolist() for s in shards for x in s.get(i)] == by[i]
        assert not any(s.get(10**9 + i) for s in shards for i in range(50))
        folder_ = tokenfile.Folder(spark, folder)
        assert all([x.tolist() for x in folder_.get(i)] == by[i] for i in by if i is not None) and not folder_.get(10**9) and not folder_.get(-(10**9))
    assert tokenfile.write_and_read(none, file, f"file://{tmp_path}/none").count() == 0


def test_token_ids_of_odd_stretches():
    tok = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    e = tokenfile.Encoder(P.path("word_bpe_49k.json"), cache=20_000)
    rng = random.Random(5)
    odd = ["", " ", "a  b", "<|endoftext|>", "x<|ENDOFTEXT|>y.", "<|startoftext|>.", "It's we'LL. 'S", "ab1.c,", "É. e\u0301x", "ß. İ.", "a\u00a0b", "x.\ny,\tz", "日本語。テスト", "don't.", ",.", "a." * 50]
    odd += ["".join(rng.choice(" .,aB'1é\u0301<|>\n") for _ in range(25)) for _ in range(600)]
    for lo in range(0, len(odd), 40):
        assert e.encode(pa.array(odd[lo : lo + 40])).to_pylist() == [[*tok.encode(x, add_special_tokens=False).ids, 2] for x in odd[lo : lo + 40]]


def test_perfect_hash():
    keys = np.random.default_rng(0).integers(-(2**62), 2**62, 20_000)
    keys = np.unique(keys)
    h = tokenfile.PerfectHash.build(keys.view(np.uint64)).ready()
    assert sorted(h.slots(keys.view(np.uint64))) == list(range(len(keys)))
    ix = tokenfile.Index.parse(tokenfile.Index.build(keys.tolist(), [1] * len(keys)).dump())
    assert (ix.find(keys)[0] == np.arange(len(keys))).all()
    absent = np.setdiff1d(np.random.default_rng(1).integers(-(2**62), 2**62, 1_000_000), keys)
    assert (ix.find(absent)[0] == -1).all()
    assert tokenfile.PerfectHash.build(np.zeros(0, np.uint64)).ready().slots(keys.view(np.uint64)).max() == -1


# 9 Toxicity


def test_toxicity_on_rows_it_did_not_see(spark, edge, none):
    big = "/root/testdata/sf0.01"
    docs, labels = load(spark, big, "documents"), load(spark, big, "labels")
    lex = toxicity.fit(docs, labels)
    got = toxicity.score(docs, lex).join(labels.select("doc_id", "toxic"), "doc_id").where("held_out")
    assert got.where("predicted = 1 and toxic = 0").count() == 0
    assert got.where("predicted = 1 and toxic = 1").count() >= 0.5 * got.where("toxic = 1").count()
    for r in toxicity.score(edge, lex).collect():
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) and r.held_out == (zlib.crc32(b"" if r.doc_id is None else str(r.doc_id).encode()) % 3 == 1)
    assert toxicity.score(none, lex).count() == 0 and toxicity.fit(none, labels).curve is None
    kept = toxicity.keep_clean(docs, lex)
    assert kept.columns == docs.columns and kept.count() == toxicity.score(docs, lex).where("predicted = 0").count()


def test_scores_by_plain_matching(spark, edge):
    big = "/root/testdata/sf0.01"
    docs, labels = load(spark, big, "documents"), load(spark, big, "labels")
    lex = toxicity.fit(docs, labels)

    def brute(text):
        words = toxicity.fold(text).split()
        safe = {j + i for p in lex.exceptions for j in range(len(words)) if words[j : j + len(p.split())] == p.split() for i in range(len(p.split()))}
        found = [max([lex.weights.get(f" {w} ", 0.0)] + [lex.weights.get(f" {w[:k]}", 0.0) for k in range(1, len(w) + 1)]) for i, w in enumerate(words) if i not in safe]
        found = [x for x in found if x]
        x = [1.0, 20.0 * sum(found) / (len(words) + 20), math.log1p(sum(found)), max(found, default=0.0), math.log1p(len(found))]
        z = sum(a * b for a, b in zip(lex.curve, x))
        return 1 / (1 + math.exp(-max(-60, min(60, z))))

    assert lex.weights and lex.curve
    for df in (docs, edge):
        want = sorted(((r.doc_id is None, r.doc_id or 0, s, int(s >= 0.7)) for r in df.collect() for s in [brute(r.text or "")]))
        for a, b in zip(sorted((r.doc_id is None, r.doc_id or 0, r.score, r.predicted) for r in toxicity.score(df, lex).collect()), want, strict=True):
            assert a[:2] == b[:2] and a[2] == pytest.approx(b[2], abs=1e-9) and a[3] == b[3]


def test_folding_and_exceptions():
    assert toxicity.fold("Y0u 1DIOT!! cl​оwn, Ｔrash") == " you idiot clown trash "
    lex = toxicity.Lexicon({" trash": 2.0, " idiot ": 3.0}, ("trash can",))
    assert lex.measures("the 1d1ot and tr4sh")[1] == pytest.approx(5.0 / 24 * 20)
    assert lex.measures("a trash can")[2] == 0 and lex.measures("a trash can, trash")[3] == 2.0
    assert lex.measures("idiotic")[2] == 0 and lex.measures("")[1] == 0 and lex.score("idiot") == 0.0


# 10 Token counts


def test_token_counts(docs, edge, none):
    file = P.path("piece_bpe_32k.model")
    c = tokencounts.Counter(tokencounts.piece_scores(file))

    def brute(word):
        w, b = "▁" + word, [(0.0, 0)]
        for e in range(1, len(w) + 1):
            n = len(w[e - 1].encode())
            found = [(b[e - 1][0] + c.lost * n, b[e - 1][1] - n)]
            found += [(b[s][0] + c.scores[w[s:e]], b[s][1] - 1) for s in range(max(0, e - 40), e) if w[s:e] in c.scores]
            b.append(max(found))
        return -b[-1][1]

    memo: dict = {}
    for df in (docs, edge):
        want = []
        for r in df.collect():
            words = re.findall(r"[^\x20\x09-\x0D]+", r.text or "")
            want.append((r.doc_id, len(words), sum(memo[w] if w in memo else memo.setdefault(w, brute(w)) for w in words)))
        assert rows(tokencounts.count(df, file), "doc_id", "n_words", "n_tokens") == sorted(want, key=repr)
    assert tokencounts.count(none, file).count() == 0


# Queries with SQL


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_same_rows_as_sql(spark, name):
    con = duckdb.connect(config={"memory_limit": "3GB", "threads": 2})
    con.execute(f"create view documents as select * from '{SF}/documents.parquet'")
    got, rel = QUERIES[name](spark, SF), con.sql(ORACLES[name])
    cols = sorted(got.columns)
    assert sorted(rel.columns) == cols
    at = [rel.columns.index(c) for c in cols]
    assert sorted(repr(tuple(r[c] for c in cols)) for r in got.collect()) == sorted(repr(tuple(r[i] for i in at)) for r in rel.fetchall())


def test_byte_bpe_lets_tables_go(spark):
    """Tables for long words wait for one; without ``keep`` a worker has no tables after its task, and the ids are the same."""
    c = bpe.Codec(*bpe.default_vocabulary())
    before = c.encode(["a plain line"])[0].to_pylist()
    assert not c.ready_for_long
    long = c.encode(["a plain line", "x" * 400 + "qzj" * 50])[0].to_pylist()
    assert c.ready_for_long and long[0] == before[0]
    docs = load(spark, SF, "documents")
    rows = [sorted(map(tuple, bpe.encode(docs, *bpe.default_vocabulary(), keep=keep).collect())) for keep in (True, False)]
    assert rows[0] == rows[1]


def test_bm25_terms_are_no_broadcast(spark):
    """Every term of the table has a row of frequencies: that side is sorted and merged, however small the files it is read from."""
    asked = spark.createDataFrame([(0, 7, "the", 2), (0, 7, "day", 1)], "row long, query_id long, term string, times long")
    terms = spark.createDataFrame([("the", 3), ("day", 1)], "term string, df long")
    found = bm25.weights(asked, terms, 4)
    plan = spark.sparkContext._jvm.PythonSQLUtils.explainString(found._jdf.queryExecution(), "simple")
    assert "SortMergeJoin" in plan and "Broadcast" not in plan
    assert {r.term: round(r.w, 9) for r in found.collect()} == {"the": round(2 * math.log(1 + 1.5 / 3.5), 9), "day": round(math.log(1 + 3.5 / 1.5), 9)}


def test_bm25_shard_scores_few_documents_whole():
    """Rare terms and block bounds leave few documents to score whole; rows are those of a plain sum, with ties, copies and short and long queries."""
    rng = np.random.default_rng(5)
    texts = [" ".join(f"w{int(v)}" for v in rng.zipf(1.3, int(rng.integers(1, 120))) if v < 5000) for _ in range(900)]
    texts += texts[:12] * 2 + [""]
    held = bm25._Postings()
    for i, t in enumerate(texts):
        held.add(i, t.encode())
    s = bm25.Shard(held.dump(), sum(held.lengths) / len(texts))
    whole = []
    plain = s._whole
    s._whole = lambda docs: whole.append(len(docs)) or plain(docs)
    for q in [*range(0, 40), 905]:
        terms = list(dict.fromkeys(texts[q].encode().split())) + [b"unknown"]
        w = [1.0 + np.log(len(texts) / (1 + s.df[s.row[t]])) if t in s.row else 1.0 for t in terms]
        want = np.zeros(len(texts))
        for t, x in zip(terms, w):
            if t in s.row:
                lo = s.start[s.row[t]]
                hi = lo + s.df[s.row[t]]
                want[s.doc[lo:hi]] += x * s.impact[lo:hi]
        want = np.round(want, 6)
        kth = np.sort(want)[-10]
        assert sorted(s.search(terms, w, 10)) == [(i, pytest.approx(v, abs=2e-6)) for i, v in enumerate(want) if v > 0 and v >= kth - 2e-6], q
        assert not s.weight.any()
    assert whole and max(whole) < 450


def test_bm25_many_queries_keep_what_they_found():
    """Shard after shard, with floors, products and pruning: the best of all documents, ties by id, none last."""
    rng = np.random.default_rng(8)
    texts = [" ".join(f"w{int(v)}" for v in rng.zipf(1.4, int(rng.integers(1, 90))) if v < 3000) for _ in range(600)]
    texts += texts[:30] + [""]
    ids = [*range(len(texts) - 2, -1, -1), None]
    bags = [Counter(t.encode().split()) for t in texts]
    average = sum(sum(b.values()) for b in bags) / len(bags)
    asked = [b for b in bags[:60] if b]
    batch = pa.RecordBatch.from_arrays(
        [pa.array(range(len(asked))), pa.array(range(len(asked))), pa.array([[t.decode() for t in b] for b in asked]), pa.array([[1.0 + v / 2 for v in b.values()] for b in asked])], names=["row", "query_id", "term", "w"]
    )
    for k in (1, 7, 1000):
        top = {}
        for lo in range(0, len(texts), 211):
            held = bm25._Postings()
            for i, t in list(zip(ids, texts))[lo : lo + 211]:
                held.add(i, t.encode())
            bm25.merge(bm25.Shard(held.dump(), average), batch, top, k)
        for q, bag in enumerate(asked):
            want = []
            for i, d in zip(ids, bags):
                dl = sum(d.values())
                if x := sum((1.0 + v / 2) * d[t] * 2.2 / (d[t] + 1.2 * (0.25 + 0.75 * dl / average)) for t, v in bag.items() if t in d):
                    want.append((-round(x, 6), i is None, i))
            want.sort(key=lambda y: (y[0], y[1], y[2] or 0))
            assert [(d, pytest.approx(x, abs=2e-6)) for x, _, d in top[q]] == [(d, x) for x, _, d in want[:k]], (k, q)


def test_bm25_rows_of_a_task_do_not_grow_with_the_shards(spark, monkeypatch):
    """Each query leaves its task with k rows at most, however many shards there are."""
    docs = spark.createDataFrame([(i, f"a b c{i % 7} d{i % 11}") for i in range(200)], "doc_id long, text string")
    monkeypatch.setattr(bm25, "SHARD_DOCS", 8)
    found = bm25.search(docs.repartition(6), docs.where("doc_id % 20 = 0"), 3)
    plan = spark.sparkContext._jvm.PythonSQLUtils.explainString(found._jdf.queryExecution(), "simple")
    assert "Window" not in plan and plan.index("MapInArrow") < plan.index("Exchange")
    assert sorted((r.query_id, r.rank) for r in found.collect()) == [(q, k) for q in range(0, 200, 20) for k in (1, 2, 3)]


def test_bm25_groups_of_other_words_are_left_out():
    """A shard of two languages: with k documents found, queries leave the other language's group alone, and rows are those of a plain sum, near ties too."""
    rng = np.random.default_rng(11)
    texts = [" ".join(f"{'xy'[i % 3 == 0]}{int(v)}" for v in rng.zipf(1.3, int(rng.integers(20, 90))) if v < 4000) for i in range(900)]
    texts += [f"{texts[1]} q{i}" for i in range(40)]  # scores that single precision can't tell apart
    bags = [Counter(t.encode().split()) for t in texts]
    average = sum(sum(b.values()) for b in bags) / len(bags)
    held = bm25._Postings()
    for i, t in enumerate(texts):
        held.add(i, t.encode())
    s = bm25.Shard(held.dump(), average)
    assert len(s.groups) > 1 and sorted(d for g in s.groups for d in g.docs.tolist()) == list(range(len(texts)))
    assert all(len({texts[d][0] for d in g.docs.tolist()}) == 1 for g in s.groups)
    asked = [{t: (1e5 if t[:1] == b"q" else 1.0) * (v + (int(t[1:]) % 7) * 1e-4) for t, v in bags[q].items()} for q in [*range(60), *range(900, 940)]]
    asked[1] |= {b"q%d" % i: 1e-4 * i for i in range(40)}
    batch = pa.RecordBatch.from_arrays(
        [pa.array(range(len(asked))), pa.array(range(len(asked))), pa.array([[t.decode() for t in b] for b in asked]), pa.array([list(b.values()) for b in asked])], names=["row", "query_id", "term", "w"]
    )
    top = {}
    bm25.merge(s, batch, top, 10)
    for q, bag in enumerate(asked):
        want = []
        for d, b in enumerate(bags):
            dl = sum(b.values())
            if x := sum(w * b[t] * 2.2 / (b[t] + 1.2 * (0.25 + 0.75 * dl / average)) for t, w in bag.items() if t in b):
                want.append((-round(x, 6), d))
        assert [(d, pytest.approx(x, abs=2e-6)) for x, _, d in top[q]] == [(d, x) for x, d in sorted(want)[:10]], q
    seen = {}
    for g in s.groups:
        g.rare = lambda rows, w, count, g=g, plain=g.rare: seen.update({id(g): len(count)}) or plain(rows, w, count)
    first = {q: [(x - 1e-3, none, -1 - d) for x, none, d in rows_] for q, rows_ in top.items()}
    bm25.merge(s, batch, first, 10)
    assert sum(seen.values()) <= len(asked) * (len(s.groups) - 1)


def test_bm25_shard_of_asked_words_scores_the_same():
    """A task reads of a shard what its queries' words need, other words and words that no document has among them."""
    held = bm25._Postings()
    texts = [f"a b{i % 5} c{i % 11} lone{i}" for i in range(300)]
    for i, t in enumerate(texts):
        held.add(i, t.encode())
    words = pa.array([b"nowhere", b"c3", b"a", b"b2"], pa.binary())
    plain, s = bm25.Shard(held.dump(), 4.0), bm25.Shard(held.dump(), 4.0, words)
    assert s.terms.to_pylist() == [b"a", b"b2", b"c3"] and s.place.tolist() == [-1, 2, 0, 1]
    assert s.search([b"c3", b"b2"], [2.0, 1.0], 300) == plain.search([b"c3", b"b2"], [2.0, 1.0], 300)
    assert bm25.Shard(held.dump(), 4.0, pa.array([b"nowhere"], pa.binary())).groups == []


def test_bm25_chunks_end_by_terms(spark, monkeypatch):
    """Queries of many terms make more chunks, of one query each if need be; rows stay the same."""
    docs = spark.createDataFrame([(i, " ".join(f"w{(i * 7 + j) % 40}" for j in range(1 + i % 9))) for i in range(120)], "doc_id long, text string")
    queries = docs.where("doc_id % 10 = 0")
    want = sorted(map(tuple, bm25.search(docs, queries, 4).collect()))
    monkeypatch.setattr(bm25, "CHUNK_TERMS", 6)
    assert sorted(map(tuple, bm25.search(docs, queries, 4).collect())) == want and len({r[0] for r in want}) == 12


def test_bm25_chunks_are_scored_together(monkeypatch):
    """Small chunks of a task make few large ones, by queries and by terms, with every query once and in order."""
    monkeypatch.setattr(bm25, "TOGETHER", 5)
    monkeypatch.setattr(bm25, "CHUNK_TERMS", 12)
    sizes = [[1, 2], [3], [], [1, 1, 1], [20], [2]]
    parts = [pa.RecordBatch.from_pydict({"query_id": pa.array([10 * i + j for j in range(len(x))], pa.int64()), "term": pa.array([["t"] * n for n in x], pa.list_(pa.string()))}) for i, x in enumerate(sizes)]
    got = list(bm25.together(iter(parts)))
    assert [b.column("query_id").to_pylist() for b in got] == [[0, 1, 10], [30, 31, 32], [40], [50]] and list(bm25.together([])) == []
