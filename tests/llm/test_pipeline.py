"""The pipeline's stages, each against its operator's own verdicts on the same rows."""

import hashlib

import corpus_pipeline as pipe
import pytest
import tiktoken

from linseg.llm import bpe, mixing, neardup, quality, toxicity
from linseg.llm.common import load

SF = "/root/testdata/sf0.001"


def ids(df):
    return sorted(r.doc_id for r in df.select("doc_id").collect())


def test_stages(spark):
    docs, labels = load(spark, SF, "documents"), load(spark, SF, "labels")
    step = {name: f for name, f in pipe.STAGES}
    a = step["quality_rules"](spark, docs, SF)
    assert ids(a) == ids(quality.assess(docs, quality.fit(docs, labels)).where("kept")) and a.columns == docs.columns
    b = step["toxicity"](spark, a, SF)
    assert ids(b) == ids(toxicity.score(a, toxicity.fit(a, labels)).where("predicted = 0")) and b.columns == docs.columns
    c = step["near_duplicates"](spark, b, SF)
    assert ids(c) == sorted({r.component_id for r in neardup.groups(b).collect()}) and c.columns == docs.columns
    d = step["mixing"](spark, c, SF)
    assert ids(d) == ids(mixing.mix(c).where("kept")) and d.columns == docs.columns
    e = step["byte_bpe"](spark, d, SF).collect()
    enc = tiktoken.Encoding("t", pat_str=bpe.default_vocabulary()[1], mergeable_ranks=bpe.Codec(*bpe.default_vocabulary()).ranks, special_tokens={})
    text = {r.doc_id: r.text for r in d.collect()}
    assert len(e) == len(text) > 0
    for r in e:
        assert list(r.token_ids) == enc.encode_ordinary(text[r.doc_id]) and r.decoded_sha256 == hashlib.sha256(text[r.doc_id].encode()).hexdigest()
    assert sorted(r.doc_id for r in pipe.run(spark, SF).collect()) == sorted(text)


@pytest.mark.parametrize("kind", ["none", "odd"])
def test_stages_on_odd_tables(spark, kind):
    rows = [] if kind == "none" else [(None, None, None, None, None), (1, "", "en", "s", 0), (2, "word " * 50, None, "s", 1), (2, "word " * 50, None, "s", 1), (3, "A plain line of words that says a few things about the day.", "en", None, 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    if kind == "odd":  # a long text, and columns named as the operators' own
        plain = "A plain line of words that says a few things about the day. "
        docs = docs.unionByName(spark.createDataFrame([(9, "\n".join(f"{plain}{i} {i * 7}." for i in range(4000)), "en", "s", 1)], docs.schema))
        docs = docs.selectExpr("*", "1.5 as __p", "'m' as __mix", "true as kept", "'d' as digest", "2L as root", "'r' as r")
    for name, stage in pipe.STAGES:
        out = stage(spark, docs, SF)
        out.count()
        if name != "byte_bpe":
            assert out.columns == docs.columns


def test_words_known_to_a_shared_worker_are_few():
    """Steps and generations bound what a worker of the last stage holds, though every word is new."""
    c = bpe.Codec(*bpe.default_vocabulary(), bpe.KNOWN_BYTES)
    words = [hashlib.md5(b"%d" % i).hexdigest()[:8] for i in range(130_000)]
    step, most = bpe.STEP_BYTES // 9, 0
    for lo in range(0, len(words), step):
        ids, back = c.encode([" ".join(words[lo : lo + step])])
        assert back[0].as_py().decode() == " ".join(words[lo : lo + step])
        most = max(most, c.store.new.bytes + c.store.old.bytes)
    assert 0 < most < 24 << 20
