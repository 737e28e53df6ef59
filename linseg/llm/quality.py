"""Quality rules: a linear-chain conditional random field labels each line content or boilerplate.

Lines are described by fixed shares and flags; the field's emission and transition weights are fitted by conditional
likelihood on a bounded sample of labelled documents.  Labels are of documents, so line labels start as the
document's and are then re-decoded inside bad documents.  Viterbi decoding labels the lines of every document, and a
document stays where enough of its words stand in content lines.

Defined results: a null text has no words and fails the base rule; lines without a word take no part; without labels
of both kinds the verdict is the base rule's; repeated rows are judged each; texts of any length are judged whole; of equal
label sequences the one that ends in content counts, and a content share equal to the threshold stays; columns other than id
and text are not read, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import keep_rows, map_texts, utf8

#: Labelled documents, of least md5 of their id, that the field is fitted on; those of over so many lines are not fitted on, so that the driver's rows are bounded.
SAMPLE, LINES = 4000, 2000
#: Share of good sample documents that the content threshold must keep.
KEEP_GOOD = 0.995
#: Base rule: fewer words fail; so does a larger share of words in repeated windows, in hundredths.
LEAST_WORDS, WINDOW, MOST_REPEATED = 10, 5, 20

_SPACE, _SYMBOLS = b" \t\n\x0b\x0c\r", b"#*$%&|<>"
_UPPER, _LOWER, _DIGIT, _PUNCT = bytes(range(65, 91)), bytes(range(97, 123)), bytes(range(48, 58)), b".,;:!?'\"()-"
FEATURES = ("bias", "short", "words", "symbols", "bars", "upper", "shout", "digits", "marks", "repeated_line", "same_words", "open_end", "long_words", "symbols_many", "same_words_many", "upper_many")


def line_features(line: bytes, words: list[bytes], again: bool) -> list[float]:
    n, k = len(line), len(words)
    symbols = sum(map(line.count, (b"#", b"*", b"$", b"%", b"&", b"|", b"<", b">"))) / k
    upper = n - len(line.translate(None, _UPPER))
    share_upper = upper / (upper + n - len(line.translate(None, _LOWER)) + 1)
    same = 1 - len(set(words)) / k
    return [
        1.0, float(k < 4), min(k, 40) / 40, min(symbols, 2.0), min(1.0, line.count(b"|") / k), share_upper, min(1.0, line.count(b"!") / k),
        (n - len(line.translate(None, _DIGIT))) / n, (n - len(line.translate(None, _PUNCT))) / n, float(again), same,
        float(words[-1][-1:] not in (b".", b"!", b"?")), float(n > 16 * k), float(symbols > 0.3), float(same > 0.5), float(share_upper > 0.5),
    ]


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words inside windows that occur twice or more, the first occurrence included; exact."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    ids = {w: i for i, w in enumerate(dict.fromkeys(words))}
    if len(ids) == len(words):
        return 0
    code = np.fromiter(map(ids.__getitem__, words), np.int64, len(words))
    grams, width = code, len(ids)
    for j in range(1, window):  # the gram so far is renumbered whenever the next word would overflow the key
        if width > (1 << 62) // len(ids):
            grams = np.unique(grams, return_inverse=True)[1]
            width = len(grams) + 1
        grams = grams[: len(code) - j] * len(ids) + code[j:]
        width *= len(ids)
    order = np.sort(grams)
    twice = order[1:][order[1:] == order[:-1]]
    if not len(twice):
        return 0
    starts = np.flatnonzero(np.isin(grams, twice))
    step = np.zeros(len(words) + 1, np.int64)
    step[starts] += 1
    np.add.at(step, starts + window, -1)
    return int((np.cumsum(step)[:-1] > 0).sum())


@dataclass
class Described:
    base: tuple[int, int, int, int, int]
    failed: bool
    features: list[list[float]]
    words: list[int]


def describe(text: bytes, lines_too: bool = True) -> Described:
    lines = text.split(b"\n")
    seen: set[bytes] = set()
    words: list[bytes] = []
    features, counts, again_n = [], [], 0
    for line in lines:
        own = line.split()
        if not own:
            continue
        again = line in seen
        again_n += again
        seen.add(line)
        words += own
        if lines_too:
            features.append(line_features(line, own, again))
            counts.append(len(own))
    points = len(text) - len(text.translate(None, _CONTINUED))
    chars = len(text) - points - sum(text.count(x) for x in _SPACE)
    n, repeated = len(words), repeated_words(words)
    base = (n, chars, len(text) - len(text.translate(None, _SYMBOLS)), again_n, repeated)
    return Described(base, n < LEAST_WORDS or 100 * repeated > MOST_REPEATED * n, features, counts)


_CONTINUED = bytes(range(128, 192))


@dataclass
class Field:
    """Log-odds weights of boilerplate, transition scores [from][to], and the least content share that stays."""

    weights: list[float]
    moves: list[list[float]]
    threshold: float

    def decode(self, features: np.ndarray) -> np.ndarray:
        """Viterbi: for each line, 1 where it is boilerplate."""
        (cc, cb), (bc, bb) = self.moves
        c = b = 0.0
        back = []
        for i, e in enumerate((features @ np.asarray(self.weights)).tolist()):
            if i:
                from_c, from_b = c + cb > b + bb, c + cc >= b + bc
                back.append((from_b, from_c))
                c, b = (c + cc if from_b else b + bc), (c + cb if from_c else b + bb) + e
            else:
                b = e
        out, at = [], int(b > c)
        for to_c, to_b in reversed(back):
            out.append(at)
            at = int(not (to_b if at else to_c))
        out.append(at)
        return np.array(out[::-1])

    def share(self, d: Described) -> float:
        if not d.words:
            return 0.0
        label = self.decode(np.asarray(d.features))
        w = np.asarray(d.words)
        return float(w[label == 0].sum() / w.sum())


def _likelihood(x: list[np.ndarray], y: list[np.ndarray], steps: int = 150, rate: float = 0.1, ridge: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    """Weights and transitions by Adam on the conditional log-likelihood; sequences run side by side, longest first."""
    order = sorted(range(len(x)), key=lambda i: -len(x[i]))
    lengths = np.array([len(x[i]) for i in order])
    rows, gold = np.concatenate([x[i] for i in order]), np.concatenate([y[i] for i in order])
    first = np.cumsum(lengths) - lengths
    at = [first[: (lengths > t).sum()] + t for t in range(lengths[0])]
    last = first + lengths - 1
    inner = np.ones(len(rows), bool)
    inner[first] = False
    pairs = np.zeros((2, 2))
    np.add.at(pairs, (gold[:-1][inner[1:]], gold[1:][inner[1:]]), 1)
    theta, m, v = np.zeros(rows.shape[1] + 4), 0.0, 0.0
    for step in range(1, steps + 1):
        w, move = theta[:-4], theta[-4:].reshape(2, 2)
        e = np.zeros((len(rows), 2))
        e[:, 1] = rows @ w
        ahead, behind = np.empty_like(e), np.zeros_like(e)
        for t, i in enumerate(at):
            ahead[i] = e[i] if not t else e[i] + np.logaddexp(ahead[i - 1, :1] + move[0], ahead[i - 1, 1:] + move[1])
        for i in at[:0:-1]:
            g = e[i] + behind[i]
            behind[i - 1] = np.logaddexp(move[:, 0] + g[:, :1], move[:, 1] + g[:, 1:])
        z = np.logaddexp(ahead[last, 0], ahead[last, 1])
        zs = np.repeat(z, lengths)
        p = np.exp(ahead + behind - zs[:, None])
        expected = np.zeros((2, 2))
        k = np.flatnonzero(inner)
        for a in (0, 1):
            for b in (0, 1):
                expected[a, b] = np.exp(ahead[k - 1, a] + move[a, b] + e[k, b] + behind[k, b] - zs[k]).sum()
        grad = np.concatenate([rows.T @ (gold - p[:, 1]), (pairs - expected).ravel()]) / len(rows) - ridge * theta
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta = theta + rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return theta[:-4], theta[-4:].reshape(2, 2)


def fit_rows(rows: list[tuple[np.ndarray, np.ndarray, int]], rounds: int = 3, keep_good: float = KEEP_GOOD) -> Field | None:
    """rows: (features, words of each line, 1 for good) of each sample document."""
    rows = [r for r in rows if len(r[0])]
    if len({r[2] for r in rows}) < 2:
        return None
    x = [r[0] for r in rows]
    y = [np.full(len(r[0]), 1 - r[2]) for r in rows]
    for k in range(rounds):
        w, move = _likelihood(x, y)
        field = Field(w.tolist(), move.tolist(), 0.0)
        if k < rounds - 1:
            for i, r in enumerate(rows):
                if not r[2]:  # a bad document may hold content lines, but its likeliest boilerplate line stays one
                    y[i] = field.decode(r[0])
                    y[i][np.argmax(r[0] @ w)] = 1
    shares = [np.sum(r[1][field.decode(r[0]) == 0]) / np.sum(r[1]) for r in rows]
    good, bad = (np.sort([s for s, r in zip(shares, rows, strict=True) if r[2] == k]) for k in (1, 0))
    ceiling = good[int((1 - keep_good) * len(good))]
    cuts = [t for t in np.linspace(0.05, 0.95, 19) if t <= ceiling] or [0.05]
    field.threshold = float(max(cuts, key=lambda t: ((bad < t).mean(), -abs(t - 0.5))))
    return field


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> Field | None:
    """Field from the labelled documents of least md5(id), at most ``sample``; only line features reach the driver."""
    picked = labels.where("quality is not null and doc_id is not null").select(F.col("doc_id").alias("id"), F.col("quality").cast("int").alias("q"))
    picked = picked.orderBy(F.md5(F.col("id").cast("string")), "id").limit(sample)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(picked), "id").select((F.col("id") * 2 + F.col("q")).alias("doc_id"), "text")

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            got = [describe(x) for x in utf8(batch, "text")]
            for d in got:  # the base rule decides on the failed ones
                if d.failed or len(d.words) > LINES:
                    d.features, d.words = [], []
            yield {"doc_id": batch.column(0), "f": [[v for row in d.features for v in row] for d in got], "w": [d.words for d in got]}

    found = map_texts(rows, "doc_id", "text", kernel, "doc_id long, f array<float>, w array<int>").collect()
    found.sort(key=lambda r: (r.doc_id, len(r.w), r.f))
    return fit_rows([(np.array(r.f, float).reshape(len(r.w), len(FEATURES)), np.array(r.w), r.doc_id % 2) for r in found])


def verdict(field: Field | None, d: Described) -> tuple[float, bool]:
    """Content share, and whether the document stays."""
    share = 1.0 if field is None else field.share(d)
    return share, not d.failed and (field is None or share >= field.threshold)


def assess(docs: DataFrame, field: Field | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document the base counts, the base rule, the share of words in content lines, and the verdict."""

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            got = [describe(x, field is not None) for x in utf8(batch, "text")]
            ends = [verdict(field, d) for d in got]
            base = list(zip(*[d.base for d in got], strict=True))
            yield {
                "doc_id": batch.column(0), "n_words": base[0], "word_chars": base[1], "n_symbols": base[2], "n_dup_lines": base[3], "n_repeat_words": base[4],
                "base_failed": [d.failed for d in got], "content_share": [s for s, _ in ends], "kept": [k for _, k in ends],
            }

    return map_texts(docs, id_col, text_col, kernel, "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, content_share double, kept boolean")


def keep_good(docs: DataFrame, field: Field | None, text_col: str = "text") -> DataFrame:
    """The rows that stay, all columns unchanged."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[bool]]]:
        for batch in batches:
            yield batch, [verdict(field, describe(x, field is not None))[1] for x in utf8(batch, text_col)]

    return keep_rows(docs, text_col, run)
