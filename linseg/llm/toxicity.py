"""Toxicity: a weighted lexicon matched by an Aho-Corasick automaton over folded text.

Folding lower-cases, replaces look-alike letters and digits, and turns the rest into single spaces.  Lexicon entries
are whole words and word beginnings with the log-odds of toxic against other training documents; at each word the
heaviest entry counts.  A word inside an exception phrase (given, or learned from clean training documents) doesn't
count.  The sum, normalised by the text's length, goes through a logistic curve fitted on training documents that the
lexicon wasn't learned from.

Defined results: null, empty and wordless texts have no match and get the curve's value at zero; without training
rows of both kinds every score is 0; repeated rows are scored each; texts of any length are matched whole; of entries that
start at one place the heaviest counts, a score of exactly 0.7 is toxic; a null id counts as the text ''; columns other than
id and text are not read, whatever their names.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, keep_rows, map_texts, texts

#: Labelled training documents, of least md5 of their id, that are used; a third of them fits the curve.
SAMPLE = 24_000
#: Weight, certainty (signed root of the likelihood ratio) and toxic documents that an entry needs.
LEAST_WEIGHT, LEAST_Z, LEAST_DOCS = 1.5, 4.5, 4
#: Lengths of word beginnings that may be entries.
STEMS = range(4, 11)
CUT = 0.7
#: Phrases in which a listed word is harmless (fixed values, already folded).
EXCEPTIONS = ("trash can", "trash bin", "clown fish", "pond scum", "pathetic fallacy", "sore loser rule")

#: Letters and digits that stand for others (fixed values): Cyrillic, Greek, full-width and digit look-alikes.
_LOOKALIKE = dict(zip("аеорсухіјѕԁһкмтвгпνορταικυχ0134578@$", "aeopcyxijsdhkmtbrnvoptaikuxoieastbas", strict=True))


def _table() -> dict[int, str]:
    table = {}
    for code in range(0x250):
        c = chr(code)
        low = c.lower()
        table[code] = low if len(low) == 1 and low.isalpha() else " "
    for code in range(0x370, 0x530):
        low = chr(code).lower()
        table[code] = low if len(low) == 1 and low.isalpha() else " "
    for code in range(0xFF21, 0xFF3B):
        table[code] = table[code + 32] = chr(code - 0xFF21 + 97)
    for code in list(table):
        if (twin := _LOOKALIKE.get(chr(code).lower())) is not None:
            table[code] = twin
    for code in (0xAD, 0x200B, 0x200C, 0x200D, 0x2060, 0xFEFF):
        table[code] = ""
    for code in range(0x2010, 0x2070):
        table.setdefault(code, " ")
    return table


_FOLD = _table()


def fold(text: str) -> str:
    """Words of folded letters, one space around each."""
    return f" {' '.join(text.translate(_FOLD).split())} "


def training(doc_id: int | None) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % 3 != 1


def entries_of(folded: str) -> set[str]:
    """Candidates of a text: ' word ' for whole words and ' stem' for word beginnings."""
    out = set()
    for w in set(folded.split()):
        out.add(f" {w} ")
        out.update([f" {w[:k]}" for k in STEMS if k <= len(w)])
    return out


@dataclass
class Lexicon:
    weights: dict[str, float] = field(default_factory=dict)
    exceptions: tuple[str, ...] = EXCEPTIONS
    curve: tuple[float, ...] | None = None

    def automaton(self):
        return _automaton(tuple(self.weights.items()), self.exceptions)

    def measures(self, text: str) -> list[float]:
        """Intercept, weight by length, log of the weight, heaviest entry, entries found."""
        folded = fold(text)
        best, safe = self.hits(folded)
        got = [w for start, w in best.items() if start not in safe]
        total, words = sum(got), folded.count(" ") - 1
        return [1.0, total / (max(words, 0) + 20.0) * 20.0, float(np.log1p(total)), max(got, default=0.0), float(np.log1p(len(got)))]

    def hits(self, folded: str) -> tuple[dict[int, float], set[int]]:
        """Heaviest weight by the word's start, and starts inside an exception phrase."""
        best: dict[int, float] = {}
        safe: set[int] = set()
        for end, (size, weight, phrase) in self.automaton().iter(folded):
            start = end - size + 1
            if phrase:
                safe.update(i for i in range(start, end) if folded[i] == " ")
            elif weight > best.get(start, 0.0):
                best[start] = weight
        return best, safe

    def score(self, text: str) -> float:
        if self.curve is None:
            return 0.0
        z = float(np.dot(self.curve, self.measures(text)))
        return 1.0 / (1.0 + float(np.exp(-max(-60.0, min(60.0, z)))))


@lru_cache(maxsize=4)
def _automaton(weights: tuple, exceptions: tuple):
    import ahocorasick

    a = ahocorasick.Automaton()
    for entry, w in weights:
        a.add_word(entry, (len(entry), w, False))
    for phrase in exceptions:
        a.add_word(f" {phrase} ", (len(phrase) + 2, 0.0, True))
    if not len(a):
        a.add_word("\0", (1, 0.0, False))
    a.make_automaton()
    return a


def choose(counts: list[tuple[str, int, int]], toxic: int, clean: int) -> dict[str, float]:
    """Entries and weights from (candidate, toxic documents, clean documents); a longer one needs a clearly larger weight than the stem it starts with."""
    found = {}
    for entry, a, b in counts:
        w = float(np.log((a + 0.5) / (toxic + 1)) - np.log((b + 0.5) / (clean + 1)))
        share = toxic / (toxic + clean)
        z = (2 * sum(n * np.log(n / ((a + b) * p)) for n, p in ((a, share), (b, 1 - share)) if n)) ** 0.5 if a + b else 0.0
        if a >= LEAST_DOCS and w >= LEAST_WEIGHT and z >= LEAST_Z:
            found[entry] = (w, z)
    kept: dict[str, float] = {}
    for entry in sorted(found, key=lambda e: (len(e), e)):
        shorter = [kept[entry[:k]] for k in range(2, len(entry)) if entry[:k] in kept]
        if not shorter or found[entry][0] > max(shorter) + 0.7:
            kept[entry] = found[entry][0]
    return dict(sorted(kept.items(), key=lambda e: (-found[e[0]][1], e[0])))


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    scale = np.maximum(np.abs(x).max(0), 1e-9)
    x, beta = x / scale, np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -60, 60)))
        step = np.linalg.solve((x.T * (p * (1 - p))) @ x + ridge * np.eye(len(beta)), x.T @ (y - p) - ridge * beta)
        beta = beta + step
        if np.abs(step).max() < 1e-8:
            break
    return beta / scale


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE, exceptions: tuple[str, ...] = EXCEPTIONS) -> Lexicon:
    """Lexicon and curve from labelled training rows.  Candidates are counted on the executors and summed by a shuffle; only entries that can pass and the curve's measures reach the driver."""
    picked = labels.where("toxic is not null and doc_id is not null and pmod(crc32(cast(cast(doc_id as string) as binary)), 3) <> 1")
    picked = picked.select(F.col("doc_id").alias("id"), F.col("toxic").cast("int").alias("toxic")).orderBy(F.md5(F.col("id").cast("string")), "id").limit(sample)
    held = F.pmod(F.crc32(F.concat(F.lit("curve"), F.col("id").cast("string")).cast("binary")), F.lit(3)) == 0
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(picked), "id")
    coded = rows.select((F.col("id") * 4 + F.col("toxic") * 2 + held.cast("int")).alias("doc_id"), "text")

    def candidates(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            by, n = (Counter(), Counter()), [0, 0]
            for code, text in zip(batch.column(0).to_pylist(), texts(batch, "text"), strict=True):
                if not code & 1:
                    n[code >> 1 & 1] += 1
                    by[code >> 1 & 1].update(entries_of(fold(text)))
            keys = list(by[0] | by[1])
            yield {"entry": ["", *keys], "toxic": [n[1], *[by[1][k] for k in keys]], "clean": [n[0], *[by[0][k] for k in keys]]}

    counted = map_texts(coded, "doc_id", "text", candidates, "entry string, toxic long, clean long").groupBy("entry").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
    counted = cut(counted)
    toxic, clean = next(((r.toxic, r.clean) for r in counted.where("entry = ''").collect()), (0, 0))
    if not toxic or not clean:
        return Lexicon(exceptions=exceptions)
    # The test of ``choose``, a little wider, so that only entries that can pass come to the driver; their number is bounded by the sample.
    weight = F.log((F.col("toxic") + 0.5) / (toxic + 1)) - F.log((F.col("clean") + 0.5) / (clean + 1))
    n, share = F.col("toxic") + F.col("clean"), toxic / (toxic + clean)
    ratio = F.col("toxic") * F.log(F.col("toxic") / (n * share)) + F.when(F.col("clean") > 0, F.col("clean") * F.log(F.col("clean") / (n * (1 - share)))).otherwise(0.0)
    found = counted.where((F.col("entry") != "") & (F.col("toxic") >= LEAST_DOCS)).where((weight >= LEAST_WEIGHT - 1e-6) & (2 * ratio >= LEAST_Z**2 - 1e-6)).collect()
    lexicon = Lexicon(choose([(r.entry, r.toxic, r.clean) for r in found], toxic, clean), exceptions)

    def phrases(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        """Pairs of words, one of them an entry, by the kind of document; and the measures of the curve's documents."""
        for batch in batches:
            by, curve = (Counter(), Counter()), []
            for code, text in zip(batch.column(0).to_pylist(), texts(batch, "text"), strict=True):
                if code & 1:
                    curve.append((code >> 1 & 1, lexicon.measures(text)))
                    continue
                folded = fold(text)
                pairs = set()
                for start in lexicon.hits(folded)[0]:
                    word, after = (folded[start + 1 :].split(" ", 2) + [""])[:2]
                    before = folded[:start].rpartition(" ")[2]
                    pairs.update({f"{before} {word}" if before else "", f"{word} {after}" if after else ""} - {""})
                by[code >> 1 & 1].update(pairs)
            keys = list(by[0] | by[1])
            yield {
                "phrase": [*keys, *[None] * len(curve)], "toxic": [*[by[1][k] for k in keys], *[y for y, _ in curve]], "clean": [*[by[0][k] for k in keys], *[0] * len(curve)],
                "x": [*[None] * len(keys), *[x for _, x in curve]],
            }

    seen = map_texts(coded, "doc_id", "text", phrases, "phrase string, toxic long, clean long, x array<double>")
    seen = cut(seen)
    harmless = seen.where("phrase is not null").groupBy("phrase").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean")).where("toxic = 0 and clean >= 5")
    learned = [r.phrase for r in harmless.collect()]
    curve = seen.where("phrase is null").select("toxic", "x").collect()
    lexicon.exceptions = (*exceptions, *sorted(set(learned) - set(exceptions)))
    y = np.array([r.toxic for r in curve], float)
    if 0 < y.sum() < len(y):
        x = np.array([r.x for r in curve])
        order = np.lexsort((*x.T, y))
        lexicon.curve = tuple(_logistic(x[order], y[order]).tolist())
    return lexicon


def score(docs: DataFrame, lexicon: Lexicon, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score in [0, 1], predicted."""

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            s = [lexicon.score(x) for x in texts(batch, "text")]
            yield {"doc_id": batch.column(0), "held_out": [not training(i) for i in batch.column(0).to_pylist()], "score": s, "predicted": [int(x >= CUT) for x in s]}

    return map_texts(docs, id_col, text_col, kernel, "doc_id long, held_out boolean, score double, predicted int")


def keep_clean(docs: DataFrame, lexicon: Lexicon, text_col: str = "text") -> DataFrame:
    """The rows that are not predicted toxic, all columns unchanged."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[bool]]]:
        for batch in batches:
            yield batch, [lexicon.score(x) < CUT for x in texts(batch, text_col)]

    return keep_rows(docs, text_col, run)
