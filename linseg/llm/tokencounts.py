"""Token counts under a unigram model, by dynamic programming shared along a trie of pre-tokens.

A pre-token is a word with the word-start sign before it.  The best segmentation of a pre-token's first j characters
depends on those characters only, so all pre-tokens that start alike share it.  Walking the distinct pre-tokens in
sorted order is a depth-first walk of their trie: the forward scores of the prefix shared with the previous one stay
on a stack, and only the rest is computed.  A terminal node keeps its word's count in a cache of bounded size.

The vocabulary file gives pieces in order of rank and no probabilities that add up, so a piece of rank r has the
score -log(r + 2.7), the Zipf-Mandelbrot form.  The segmentation of greatest score counts; equal scores take fewer
tokens.  A character that no piece covers costs its UTF-8 bytes in tokens, at a score below every piece.

Defined results: a null or blank text has no tokens; repeated rows are counted each; an empty table gives no rows;
words of any length are processed whole; columns other than id and text are not read.
"""

from __future__ import annotations

import gc
import math
from collections.abc import Iterable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_texts, utf8

SHIFT = 2.7
START = "▁"
#: Distinct pre-tokens whose counts are remembered in a worker.
CACHE = 600_000


def piece_scores(model_file: str) -> dict[str, float]:
    """Scores of the ordinary pieces of a sentencepiece file, by rank."""
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=model_file)
    plain = (i for i in range(m.get_piece_size()) if not (m.is_control(i) or m.is_unknown(i) or m.is_byte(i)))
    return {m.id_to_piece(i): -math.log(r + SHIFT) for r, i in enumerate(plain)}


class Counter:
    """Forward scores over one vocabulary."""

    def __init__(self, scores: dict[str, float], cache: int = CACHE):
        self.scores, self.cache, self.counts = scores, cache, {}
        #: By last character, the lengths that pieces have, so that few substrings are looked up.
        sizes: dict[str, set[int]] = {}
        for piece in scores:
            sizes.setdefault(piece[-1], set()).add(len(piece))
        self.sizes = {c: sorted(x) for c, x in sizes.items()}
        self.lost = min(scores.values(), default=0.0) - 10.0

    def walk(self, words: Iterable[str]) -> Iterator[tuple[str, int, float]]:
        """(word, tokens, score) of distinct words, which come sorted; the stack holds the path of the trie."""
        scores, sizes, lost = self.scores, self.sizes, self.lost
        best, used, last = [0.0], [0], ""
        for word in words:
            j, most = 0, min(len(word), len(last))
            while j < most and word[j] == last[j]:
                j += 1
            del best[j + 1 :], used[j + 1 :]
            for end in range(j + 1, len(word) + 1):
                c = word[end - 1]
                n = len(c.encode("utf-8", "surrogatepass"))
                top, count = best[end - 1] + lost * n, used[end - 1] + n
                for size in sizes.get(c, ()):
                    if size > end:
                        break
                    if (s := scores.get(word[end - size : end])) is not None:
                        s += best[end - size]
                        k = used[end - size] + 1
                        if s > top or (s == top and k < count):
                            top, count = s, k
                best.append(top)
                used.append(count)
            last = word
            yield word, used[-1], best[-1]

    def count(self, group: list[bytes]) -> list[tuple[int, int]]:
        """Words and tokens of each text."""
        split = [x.split() for x in group]
        if len(self.counts) > self.cache:
            self.counts.clear()
        known = self.counts
        back = {START + w.decode("utf-8", "surrogatepass"): w for w in set().union(*split) - known.keys()}
        for word, n, _ in self.walk(sorted(back)):
            known[back[word]] = n
        return [(len(words), sum(map(known.__getitem__, words))) for words in split]


@lru_cache(maxsize=2)
def counter(model_file: str) -> Counter:
    return Counter(piece_scores(model_file))


def count(df: DataFrame, model_file: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_tokens of every row."""

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        gc.disable()
        c = counter(model_file)
        for batch in batches:
            got = c.count(utf8(batch, "text"))
            yield {"doc_id": batch.column(0), "n_words": [w for w, _ in got], "n_tokens": [n for _, n in got]}

    return map_texts(df, id_col, text_col, kernel, "doc_id long, n_words long, n_tokens long")
