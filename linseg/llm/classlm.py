"""Language-model scores by class-based n-grams (word classes by exchange clustering).

Training counts every word of every training document; the counts stay a table.  Exchange clustering moves each of
the ``HEAD`` most frequent words between classes while that raises the likelihood of the class bigrams; then each of the
``CLUSTERED`` most frequent ones moves to the class that raises it most, from the words' neighbours in all training documents,
counted by class where they stand.  Words beyond those, of which a corpus has no end, have their class by shape (length,
first and last byte), so that a word unseen in training has one too.  Class bigrams are then counted anew.  A text's probability is the product over its tokens of class transition (discounted, the
rest by class frequency) and word emission (in the shape classes with one added to each count and one more for unseen words).

Counts of words up to ``COMMON`` in number go to the executors as a dictionary; those of all other words are
joined to the documents that use them, so no table that grows with the corpus is broadcast.

Defined results: a null text is empty and has its end token alone; without training rows every count is 0; a null id
counts as the text ''; repeated rows are scored each and counted each; texts of any length count whole; of equally frequent
words those of lesser bytes come first, and of equally good classes that of least number; columns other than id and text are
not read, whatever their names.
"""

from __future__ import annotations

import gc
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, arrow_schema, cut, pieces, utf8
from .stretches import split

#: Words that are exchanged one by one, classes that they get, sweeps over them, words that get a class of these, words whose counts are broadcast.
HEAD, CLASSES, SWEEPS, CLUSTERED, COMMON = 2000, 64, 6, 50_000, 200_000
#: Neighbours that a task gathers before it adds them up.
GATHER = 2_000_000
#: Mass of a class bigram that is left to the class's own frequency.
DISCOUNT = 0.7
SHAPES = 32
#: Distinct words that a counting task holds before it hands them on.
HOLD = 400_000
_LENGTHS = bytes([0, 0, 0, 0, 1, 1, 1, 2, 2, 2, 3, 3, 4, 4, 5, 5, 6, 6, 6, 6, 7])
_ENDS = frozenset(b".,;:!?|*$%&#")


def shape(word: bytes) -> int:
    return _LENGTHS[min(len(word), 20)] * 4 + (word[-1] in _ENDS) * 2 + (not 97 <= word[0] <= 122)


def held_out(doc_id) -> F.Column:
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(7)) == 2


def _words(text: bytes) -> list[bytes]:
    return text.translate(LOWER).split()


def word_counts(train: DataFrame) -> DataFrame:
    """word, c of the column ``text``; summed in the task first, then by a shuffle."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()).cast(pa.string()), pa.array(list(held.values()), pa.int64())], names=["word", "c"])

        for batch in pieces(batches, "text"):
            for text in utf8(batch, "text"):
                held.update(_words(text))
            if len(held) > HOLD:
                yield out()
                held.clear()
        if held:
            yield out()

    return train.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "word string, c long").groupBy("word").agg(F.sum("c").alias("c"))


def most_frequent(counts: DataFrame, most: int) -> list[tuple[bytes, int]]:
    """The words over the least count that leaves ``most`` or fewer, by frequency; the bound comes from a small histogram."""
    level = F.floor(F.log2("c") * 64).cast("int")
    steps = sorted(((r.level, r.n) for r in counts.groupBy(level.alias("level")).agg(F.count("*").alias("n")).collect()), reverse=True)
    total, least = 0, None
    for at, n in steps:
        if total + n > most:
            break
        total, least = total + n, at
    if least is None:
        return []
    got = counts.where(level >= least).toArrow()
    return sorted(((w.encode(), c) for w, c in zip(got["word"].to_pylist(), got["c"].to_pylist(), strict=True)), key=lambda x: (-x[1], x[0]))


def _tokens(column: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Distinct lower-cased words of the texts, the number of each word in turn, and the texts' lengths."""
    found, code, n = split(pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(column, ""))))
    words = found.to_pylist()
    if "" not in words:  # what stands before leading and behind trailing white space
        return words, code, n
    real = code != words.index("")
    edges = np.concatenate([[0], np.cumsum(real)])
    ends = np.cumsum(n)
    return words, code[real], edges[ends] - edges[ends - n]


def _sequence(of: np.ndarray, n: np.ndarray, end: int) -> np.ndarray:
    """The texts' tokens end to end, with ``end`` before, between and behind them."""
    return np.append(np.insert(of, np.cumsum(n) - n, end), end)


def pair_counts(train: DataFrame, words: list[bytes], of: np.ndarray, shapes: int) -> np.ndarray:
    """Counts of neighbours by class (rows: the former).  of: class of each word; other words have class ``shapes`` + shape; the last class is a text's end.

    Tasks add into a matrix and hand on its nonzero cells; their sums, of that number at most, come to the driver.
    """
    size = shapes + SHAPES + 1
    shared = train.sparkSession.sparkContext.broadcast({w.decode(): int(c) for w, c in zip(words, of, strict=True)})

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        get = shared.value.get
        table = np.zeros(size * size, np.int64)
        for batch in pieces(batches, "text"):
            found, code, n = _tokens(batch.column(0))
            own = np.array([c if (c := get(w)) is not None else shapes + shape(w.encode()) if w else 0 for w in found], np.int64)
            at = _sequence(own[code], n, size - 1)
            table += np.bincount(at[:-1] * size + at[1:], minlength=size * size)
        k = np.flatnonzero(table)
        for lo in range(0, len(k), 100_000):
            part = k[lo : lo + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array(table[part], pa.int64())], names=["pair", "n"])

    got = train.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(size * size)
    out[got["pair"].to_numpy()] = got["n"].to_numpy()
    return out.reshape(size, size)


def bigrams(train: DataFrame, head: list[bytes]) -> np.ndarray:
    """``pair_counts`` with a class for each head word."""
    return pair_counts(train, head, np.arange(len(head)), len(head))


def place_rest(train: DataFrame, words: list[bytes], first: int, of: np.ndarray, g: np.ndarray, classes: int) -> np.ndarray:
    """Class of each of ``words`` from place ``first`` on (those before have ``of``): the one whose bigrams ``g`` gain most by it.

    A task adds up the classes before and behind each word; the vectors, one a word and task at most, meet by word, where the
    best class is found; a number for each word comes to the driver.
    """
    k = len(g)
    shared = train.sparkSession.sparkContext.broadcast(({w.decode(): i for i, w in enumerate(words)}, of, g))

    def gather(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place, of, _ = shared.value
        get, table, held, size = place.get, np.zeros(len(words[first:]) * 2 * k, np.uint32), [], 0

        def add() -> None:
            cells, times = np.unique(np.concatenate(held), return_counts=True)
            table[cells] += times.astype(np.uint32)
            held.clear()

        for batch in pieces(batches, "text"):
            found, code, n = _tokens(batch.column(0))
            word = np.array([i if (i := get(w)) is not None else -1 for w in found], np.int64)
            own = np.array([of[i] if 0 <= i < first else classes + shape(w.encode()) if w else 0 for w, i in zip(found, word.tolist(), strict=True)], np.int64)
            at, who = _sequence(own[code], n, k - 1), _sequence(word[code], n, -1)
            here = np.flatnonzero(who >= first)
            cell = (who[here] - first) * 2 * k
            held += [cell + at[here - 1], cell + k + at[here + 1]]
            size += 2 * len(here)
            if size > GATHER:
                add()
                size = 0
        if held:
            add()
        rows = table.reshape(-1, 2 * k)
        some = np.flatnonzero(rows.any(1))
        for lo in range(0, len(some), 5000):
            part = some[lo : lo + 5000]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array([r.tobytes() for r in rows[part]], pa.binary())], names=["word", "v"])

    def choose(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = shared.value[2]
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for w, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                x = np.frombuffer(v, np.uint32).astype(np.float64)
                sums[w] = sums[w] + x if w in sums else x
        if sums:
            best = [int(np.argmax(_gain(g, classes, x[k:], x[:k], 0.0))) for x in sums.values()]
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array(best, pa.int64())], names=["word", "class"])

    met = train.select(F.col("text").cast("string").alias("text")).mapInArrow(gather, "word long, v binary").repartition("word")
    got = met.mapInArrow(choose, "word long, class long").toArrow()
    out = classes + np.array([shape(w) for w in words[first:]], np.int64)
    out[got["word"].to_numpy()] = got["class"].to_numpy()
    return out


def _xlogx(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1.0))


def _gain(g: np.ndarray, classes: int, right: np.ndarray, left: np.ndarray, own: float) -> np.ndarray:
    """What the class-bigram likelihood gains when a word that stands in no class joins each: counts behind and before it by class, and of itself."""
    rows, cols = g[:classes], g[:, :classes].T
    gain = (_xlogx(rows + right) - _xlogx(rows)).sum(1) + (_xlogx(cols + left) - _xlogx(cols)).sum(1)
    d = np.arange(classes)
    diag = g[d, d]
    gain += 2 * _xlogx(diag) - _xlogx(diag + right[d]) - _xlogx(diag + left[d]) + _xlogx(diag + right[d] + left[d] + own) - _xlogx(diag)
    out_n, in_n = g[:classes].sum(1), g[:, :classes].sum(0)
    return gain - (_xlogx(out_n + right.sum() + own) - _xlogx(out_n) + _xlogx(in_n + left.sum() + own) - _xlogx(in_n))


def exchange(table: np.ndarray, head: int, classes: int = CLASSES, sweeps: int = SWEEPS) -> np.ndarray:
    """Class of each row of ``table``: the first ``head`` (by frequency) are moved between ``classes``, each further row is a class of its own.

    A word moves to the class that gives the largest class-bigram likelihood, the least-numbered at ties; sweeps
    end when none moves.
    """
    size = len(table)
    classes = max(1, min(classes, head)) if head else 0
    of = np.concatenate([np.arange(head) % classes if head else np.zeros(0, int), classes + np.arange(size - head)]).astype(int)
    k = classes + size - head
    member = np.zeros((size, k))
    member[np.arange(size), of] = 1
    to, fro = table @ member, table.T @ member  # of each word: counts of the classes after and before it
    g = member.T @ to
    for _ in range(sweeps):
        moved = 0
        for w in range(head):
            a, own = of[w], table[w, w]
            right, left = to[w].copy(), fro[w].copy()
            right[a] -= own
            left[a] -= own
            g[a] -= right
            g[:, a] -= left
            g[a, a] -= own
            gain = _gain(g, classes, right, left, own)
            b = int(np.argmax(gain))
            if gain[b] <= gain[a] + 1e-9:
                b = a
            g[b] += right
            g[:, b] += left
            g[b, b] += own
            if b != a:
                moved += 1
                of[w] = b
                to[:, a] -= table[:, w]
                to[:, b] += table[:, w]
                fro[:, a] -= table[w]
                fro[:, b] += table[w]
        if not moved:
            break
    return of


class Model:
    """What scoring needs: arrays by word of the dictionary, transitions by class, totals."""

    def __init__(self, common: list[tuple[bytes, int]], of: np.ndarray, shapes: int, pairs: np.ndarray, types: np.ndarray, n: int, v: int, ends: int, discount: float = DISCOUNT):
        """of: classes of the first common words; the others have class ``shapes`` + shape.  pairs: class bigrams.  types: distinct training words of each shape outside ``of``."""
        self.n, self.v, self.ends = n, v, ends
        k, m = len(pairs), len(of)
        self.end = k - 1
        self.shape_class = shapes + np.arange(SHAPES)
        before, after = pairs.sum(1), pairs.sum(0)
        own = (after + 1) / (after.sum() + k)  # also for classes that training never saw
        some = (pairs > 0).sum(1)
        with np.errstate(divide="ignore", invalid="ignore"):
            p = np.maximum(pairs - discount, 0) / before[:, None] + (discount * some / before)[:, None] * own
        self.moves = np.log10(np.where(before[:, None] > 0, p, own))
        size = np.zeros(k)
        counts = np.array([c for _, c in common], float)
        np.add.at(size, of, counts[:m])
        self.shape_base = np.log10(after[self.shape_class] + types + 1)
        self.words = {w: i for i, (w, _) in enumerate(common)}
        marks = np.array([shape(w) for w, _ in common[m:]], int)
        self.word_class = np.concatenate([of, self.shape_class[marks]]).astype(np.int32)
        self.log_count = np.log10(counts + 1)
        self.emit = np.concatenate([np.log10(counts[:m] / size[of]), self.log_count[m:] - self.shape_base[marks]])

    def parts(self, text: bytes) -> tuple[int, float, float, list[bytes]]:
        """Tokens, sum of log10(c + 1) over dictionary words and the end, log10 probability but for the counts of the other words, those words."""
        words = _words(text)
        at = list(map(self.words.get, words))
        rare = [w for w, i in zip(words, at, strict=True) if i is None] if None in at else []
        log_end = float(np.log10(self.ends + 1))
        if not rare:
            i = np.array(at, np.int64)
            c, total, s = self.word_class[i], self.log_count[i].sum(), self.emit[i].sum()
        else:
            shapes = np.fromiter(map(shape, rare), np.int64, len(rare))
            i = np.array([-1 if x is None else x for x in at], np.int64)
            here = i >= 0
            c = np.empty(len(i), np.int32)
            c[here], c[~here] = self.word_class[i[here]], self.shape_class[shapes]
            total, s = self.log_count[i[here]].sum(), self.emit[i[here]].sum() - self.shape_base[shapes].sum()
        s += self.moves[np.concatenate([[self.end], c]), np.concatenate([c, [self.end]])].sum()
        return len(words) + 1, float(total) + log_end, float(s), rare


def fit(train: DataFrame, counts: DataFrame, head: int = HEAD, classes: int = CLASSES, common: int = COMMON, clustered: int = CLUSTERED) -> Model:
    """counts: ``word_counts`` of the same rows."""
    ends = train.count()
    total, v = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    known = most_frequent(counts, common)
    words = [w for w, _ in known]
    table, head = bigrams(train, words[:head]), min(head, len(words))
    of = exchange(table, head, classes)
    member = np.eye(int(of.max()) + 1)[of]
    pairs, shapes = member.T @ table @ member, int(of.max()) - SHAPES
    of = of[:head]
    if shapes and len(words[:clustered]) > head:
        of = np.concatenate([of, place_rest(train, words[:clustered], head, of, pairs, shapes)])
        pairs = pair_counts(train, words[:clustered], of, shapes)
    outside = _shape_types(counts) - np.bincount([shape(w) for w in words[: len(of)]], minlength=SHAPES)
    return Model(known, of, shapes, pairs, outside, total + ends, v + (ends > 0), ends)


def _shape_types(counts: DataFrame) -> np.ndarray:
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(SHAPES, np.int64)
        for batch in batches:
            n += np.bincount([shape(w) for w in utf8(batch, "word")], minlength=SHAPES)
        yield pa.RecordBatch.from_arrays([pa.array(range(SHAPES), pa.int32()), pa.array(n)], names=["s", "n"])

    out = np.zeros(SHAPES, np.int64)
    for r in counts.select("word").mapInArrow(run, "s int, n long").groupBy("s").agg(F.sum("n").alias("n")).collect():
        out[r.s] = r.n
    return out


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", head: int = HEAD, classes: int = CLASSES, common: int = COMMON, clustered: int = CLUSTERED) -> DataFrame:
    """Per row: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, both log10."""
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).withColumn("held_out", held_out(F.col("doc_id")))
    train = rows.where("not held_out").select("text")
    counts = cut(word_counts(train))
    model = fit(train, counts, head, classes, common, clustered)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    fields = "row long, doc_id long, held_out boolean, n_tokens long, n_rare long, sum_log double, path double, rare array<string>"
    schema = arrow_schema(fields)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gc.disable()
        m = shared.value
        for batch in pieces(batches, "text"):
            n, total, path, rare = zip(*[m.parts(x) for x in utf8(batch, "text")], strict=True)
            words = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, rare)]), pa.int32()), pa.array([w for r in rare for w in r], pa.binary()).cast(pa.string()))
            cols = [batch.column(0), batch.column(1), batch.column(3), pa.array(n, pa.int64()), pa.array(list(map(len, rare)), pa.int64()), pa.array(total), pa.array(path), words]
            yield pa.RecordBatch.from_arrays([c.cast(f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)

    parts = cut(rows.mapInArrow(run, fields))
    used = parts.select("row", F.explode("rare").alias("word")).groupBy("row", "word").agg(F.count("*").alias("times"))
    of_rare = used.join(counts, "word", "left").groupBy("row").agg(F.sum(F.when(F.col("c").isNull(), F.col("times")).otherwise(0)).alias("unknown"), F.sum(F.col("times") * F.log10(F.coalesce("c", F.lit(0)) + 1)).alias("rare_log"))
    rare_log, unknown = F.coalesce("rare_log", F.lit(0.0)), F.coalesce("unknown", F.lit(0))
    no_end = int(model.ends == 0)
    return parts.drop("rare").join(of_rare, "row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("n_tokens") - unknown - no_end).alias("n_known"), F.lit(int(model.n)).cast("long").alias("train_tokens"),
        (F.col("sum_log") + rare_log - F.col("n_tokens") * F.lit(float(np.log10(model.n + model.v + 1)))).alias("base_score"), (F.col("path") + rare_log).alias("score"),
    )
