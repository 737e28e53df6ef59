"""The pipeline's near-duplicate stage against a brute force over all pairs."""

import random
from itertools import combinations

import corpus_pipeline as pipe
import numpy as np
import pytest

from linseg.llm import graph, neardup, simhash
from linseg.llm.common import LOWER, load

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def brute(rows):
    """Least id of every row's group, by sets of the words themselves."""

    def grams(text):
        w = (text or "").encode().translate(LOWER).split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    found = [grams(t) for _, t in rows]
    p = list(range(len(rows)))

    def root(x):
        while p[x] != x:
            x = p[x]
        return x

    for i, j in combinations(range(len(rows)), 2):
        both = len(found[i] & found[j])
        if found[i] == found[j] or 5 * both >= 4 * (len(found[i]) + len(found[j]) - both) > 0:
            p[root(i)] = root(j)
    least: dict = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[root(i)] = min(d, least.get(root(i), d))
    return [(d, least.get(root(i))) for i, (d, _) in enumerate(rows)]


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(7)
    word = [f"w{i}" for i in range(400)]
    notice = [rng.choice(word) for _ in range(60)]
    out = []
    for base in range(12):
        text = [rng.choice(word) for _ in range(rng.choice([30, 80, 300]))] + (notice if base % 2 else [])
        for _ in range(6):
            t = list(text)
            for _ in range(rng.randint(0, 6)):
                t[rng.randrange(len(t))] = rng.choice(word)
            out.append(" ".join(t))
    out += ["Five Words make one shingle", "five words make one\nshingle", "", None, "  \t", "short", "a b c d e f g"]
    rng.shuffle(out)
    return [*enumerate(out), (None, out[0]), (None, "no id here at all today"), (3, out[3])]


@pytest.mark.parametrize("group", [neardup.GROUP, 2])
@pytest.mark.parametrize("often", [False, True])
def test_every_similar_pair_is_linked(spark, rows, group, often):
    last = None
    if often:  # the commonest shingles last, as in a large table
        g, n = np.unique(np.concatenate([neardup.shingles((t or "").encode()) for _, t in rows]), return_counts=True)
        last = g[n > 3], np.argsort(np.argsort(n[n > 3], kind="stable"), kind="stable")
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.component_id) for r in neardup.groups(df, group=group, last=last).collect()), key=repr)
    assert got == sorted(brute(rows), key=repr)
    assert neardup.groups(df.limit(0)).count() == 0


def test_stage_drops_edited_copies(spark):
    """Up to three of 200 words changed: similarity 0.89 or more, 3-word fingerprints further apart than three bits."""
    rng = random.Random(1)
    base = [f"t{rng.randrange(5000)}" for _ in range(200)]
    texts = [base, [*base[:100], "new", *base[101:]], [*base[:40], "x", "y", *base[42:150], "z", *base[151:]], [f"u{i}" for i in range(200)]]
    rows = [(i, " ".join(t), "en", "s", 0) for i, t in enumerate(texts)]
    stage = dict(pipe.STAGES)["near_duplicates"]
    kept = stage(spark, spark.createDataFrame(rows, SCHEMA), "").collect()
    assert sorted(r.doc_id for r in kept) == [0, 3] == sorted({c for _, c in brute([r[:2] for r in rows])})


def test_stage_on_the_given_documents(spark):
    docs = load(spark, SF, "documents")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    kept = dict(pipe.STAGES)["near_duplicates"](spark, docs, SF)
    assert sorted(r.doc_id for r in kept.collect()) == sorted({c for _, c in brute(rows)}) and kept.columns == docs.columns


def test_parities_never_show_too_many_differences():
    rng = np.random.default_rng(3)
    for n in (0, 1, 5, 300, 2000):
        a = np.unique(rng.integers(-(2**63), 2**63 - 1, n))
        b = np.unique(np.concatenate([a[: n // 2 + 1], rng.integers(-(2**63), 2**63 - 1, n // 3)]))
        assert neardup.differences(neardup.parity(a), neardup.parity(b)) <= len(np.setxor1d(a, b)) and neardup.differences(neardup.parity(a), neardup.parity(a)) == 0


def test_fingerprints_come_first(spark, rows):
    """The covering tables join exactly the classes whose five-word fingerprints a chain of up to three bits joins."""
    rng = random.Random(5)
    base = [f"v{rng.randrange(900)}" for _ in range(700)]
    more = [" ".join([*base[:at], "new", *base[at + 1 :]]) for at in range(0, 700, 7)]
    docs = neardup.prefixes(spark.createDataFrame([*rows, *enumerate(more, 1000)], "doc_id long, text string"), "doc_id", "text", (np.zeros(0, np.int64), np.zeros(0, np.int64))).cache()
    given = {r.doc_id: r.fp for r in docs.where("doc_id >= 1000").collect()}
    assert all(given[i] == simhash.signed(simhash.fingerprint(x.encode(), 5)) for i, x in enumerate(more, 1000))
    one = {r.s: r.fp for r in docs.groupBy("s").agg({"fp": "min"}).withColumnRenamed("min(fp)", "fp").collect()}
    names = sorted(one)
    met = [(r.a, r.b) for r in neardup._met_by_fingerprint(docs).collect()]
    near = [(a, b) for a, b in combinations(names, 2) if ((one[a] ^ one[b]) & (2**64 - 1)).bit_count() <= 3]

    def least(edges):
        a, b = graph.forest(np.array([e[0] for e in edges]), np.array([e[1] for e in edges]))
        return dict(zip(a.tolist(), b.tolist(), strict=True))

    assert near and least(met) == least(near)
