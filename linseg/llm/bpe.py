"""Byte-level BPE encoding and decoding by DuckDB recursive queries inside each partition.

A partition's texts are cut into stretches; the stretches not seen yet become token-position rows of a DuckDB
table.  A recursive query joins neighbouring rows with the merge table and contracts, in every word at once, the
leftmost pair of least rank, until no pair is left that can merge.  An ordered aggregation over the vocabulary
turns ids back into bytes.  Results of a stretch are remembered in a store bounded by bytes (``stretches``).

Defined results: a null text is the empty text (no tokens); repeated rows are encoded each; an empty table gives
no rows; a text or a single word of any length is encoded whole; of equal pairs the leftmost goes first; the special
tokens' strings are ordinary text; columns other than id and text are never read, whatever their names.
"""

from __future__ import annotations

import base64
import gc
import hashlib
import os
import re
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_texts, pieces, release_memory, texts
from .stretches import GENERATION, Store, joined, of_texts, payload, ragged, run_lengths

#: Unicode White_Space, as the pattern's white-space class means it.
_WS = "\t\n\x0b\x0c\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Where a cut before a space would part a run of white space that the pattern sees as one.
_RUN = re.compile(rf"[{_WS}] (?:[{_WS}]|\Z)")
#: Stretches that the pattern never joins: a word with the space before it, or a run of white space.
_STRETCH = re.compile(rf" ?[^{_WS}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+")
#: Pieces of more bytes than this are contracted by the query for long words.
LONG = 160
#: Pieces, and their bytes, that one recursive query takes.
BATCH, BATCH_BYTES = 16_000, 1 << 20
#: Text bytes of a step of a worker that shares its memory with earlier stages' workers, and of each generation of words known to it.
STEP_BYTES, KNOWN_BYTES = 256 << 10, 2 << 20

#: State rows: word, position, next position, token, next token, rank of the two, still live.
_CONTRACT = """
with recursive state(w, pos, nxt, tok, ntok, rk, live) as (
  select i.w, i.pos, i.pos + 1, i.tok, i.ntok, g.m, true
  from (select *, lead(tok) over (partition by w order by pos) ntok from word_rows) i
  left join merges g on g.ab = i.tok::bigint * 131072 + i.ntok
  union all (
    with least as materialized (
      select w, min(rk::bigint * 4294967296 + pos * 65536 + nxt) k from state where live group by w),
    pick as materialized (
      select l.w, (l.k >> 32)::int rk, ((l.k >> 16) & 65535)::int lo, (l.k & 65535)::int hi, s.nxt, s.ntok
      from least l left join state s on s.live and s.w = l.w and s.pos = (l.k & 65535)),
    moved as (
      select s.w, s.pos, s.rk, p.rk is not null live, s.pos = p.lo or s.nxt = p.lo touched,
        case when s.pos = p.lo then p.nxt else s.nxt end nxt,
        case when s.pos = p.lo then p.rk else s.tok end tok,
        case when s.pos = p.lo then p.ntok when s.nxt = p.lo then p.rk else s.ntok end ntok
      from state s join pick p on p.w = s.w
      where s.live and s.pos is distinct from p.hi)
    select v.w, v.pos, v.nxt, v.tok, v.ntok, case when v.touched then g.m else v.rk end, v.live
    from moved v left join merges g on g.ab = case when v.touched then v.tok::bigint * 131072 + v.ntok end))
select w, pos, tok from state where not live
"""

#: The same fixpoint for long words, many contractions a step.  Here a token is its id with its first and its last byte above it.
#: What may yet take a pair's left part is the token before it, or a longer one that ends with that token and the byte
#: before it; likewise on the right.  ``lefts`` and ``rights`` hold the least rank of the merges of such longer ones.  A run of
#: pairs of one rank that no lower merge can reach, and whose merged tokens join nothing at a lower rank, ends up contracted
#: from the left whatever happens elsewhere: a step contracts all such runs beside the leftmost pair of least rank.
_CONTRACT_LONG = """
with recursive state(w, pos, tok, live) as (
  select w, pos, b.code, true from word_rows join codes b on b.id = tok
  union all (
    with pairs as materialized (
      select n.*, g.code, g.m, lag(g.m) over o m_before, lead(g.m) over o m_after from (
        select w, pos, tok, lag(tok) over o & 131071 x, lag(tok, 2) over o >> 25 p, lead(tok) over o & 131071 nt, lead(tok, 2) over o & 131071 y,
          (lead(tok, 3) over o >> 17) & 255 z, row_number() over o idx from state where live window o as (partition by w order by pos)) n
      left join merges g on g.ab = (n.tok & 131071) * 131072 + n.nt window o as (partition by w order by idx)),
    least as (select w, min(m) m, arg_min(idx, m::bigint * 4294967296 + idx) first_idx from pairs group by w),
    reach as (
      select q.w, q.idx, q.m, q.idx - row_number() over (partition by q.w, q.m order by q.idx) run,
        least(coalesce(m_before, 2147483647), coalesce(l.m, 2147483647)) a, least(coalesce(m_after, 2147483647), coalesce(r.m, 2147483647)) b,
        least(coalesce(lx.m, 2147483647), coalesce(l2.m, 2147483647), coalesce(rx.m, 2147483647), coalesce(r2.m, 2147483647)) c
      from pairs q
      left join lefts l on l.k = (q.p * 131072 + q.x) * 131072 + (q.tok & 131071)
      left join rights r on r.k = (q.nt * 131072 + q.y) * 256 + q.z
      left join merges lx on lx.ab = q.x * 131072 + q.m
      left join lefts l2 on l2.k = (q.p * 131072 + q.x) * 131072 + q.m
      left join merges rx on rx.ab = q.m::bigint * 131072 + q.y
      left join rights r2 on r2.k = (q.m::bigint * 131072 + q.y) * 256 + q.z
      where q.m is not null),
    chosen as materialized (
      select w, idx from (
        select w, idx, row_number() over (partition by w, m, run order by idx) nth,
          bool_and(a >= m and b >= m and c > m) over (partition by w, m, run) and first_value(a > m) over (partition by w, m, run order by idx) free from reach)
      where free and nth % 2 = 1
      union select w, first_idx from least where m is not null),
    marked as (
      select q.*, c.idx is not null hit, lag(c.idx) over (partition by q.w order by q.idx) is not null gone, l.m is not null more
      from pairs q join least l on l.w = q.w left join chosen c on c.w = q.w and c.idx = q.idx)
    select w, pos, case when hit then code else tok end, more from marked where not gone))
select w, pos, (tok & 131071)::int tok from state where not live
"""

#: A word's ids in order, and the bytes that the vocabulary gives for them.
_READ = """
select t.w, list(t.tok order by t.pos) ids, list(v.piece order by t.pos) pieces
from ({rows}) t join vocab v on v.id = t.tok group by t.w order by t.w
"""


class Codec:
    """Encoder and decoder over one rank file; one in a worker process.  A result has two columns: ids, and the bytes decoded from them."""

    def __init__(self, rank_file: str, pattern: str, cache: int = GENERATION):
        import duckdb
        import regex

        with open(rank_file, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in (x.split() for x in lines if x.strip())}
        if max(self.ranks.values(), default=0) >= 1 << 17:
            raise ValueError("the merge table's keys hold ranks below 131072")
        self.pattern = regex.compile(pattern)
        self.store = Store([pa.LargeListArray.from_arrays([0], pa.array([], pa.int32())), pa.array([], pa.large_binary())], cache)
        left, right, rank = [], [], []
        for token, r in self.ranks.items():
            for i in range(1, len(token)):
                a, b = self.ranks.get(token[:i]), self.ranks.get(token[i:])
                if a is not None and b is not None:
                    left.append(a), right.append(b), rank.append(r)
        self.byte = np.array([self.ranks[bytes([i])] for i in range(256)], np.int32)
        # Spilled rows are the query's own scratch, so they may lie in the executor's temporary folder.
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": "200MB", "temp_directory": os.path.join(os.environ.get("TMPDIR", "/tmp"), "linseg-duckdb")})
        code = {r: r | t[0] << 17 | t[-1] << 25 for t, r in self.ranks.items()}
        self._table("merges", {"ab": np.array(left, np.int64) * 131072 + np.array(right, np.int64), "m": np.array(rank, np.int32), "code": np.array([code[r] for r in rank], np.int64)})
        self._table("codes", {"id": np.array(list(code), np.int32), "code": np.array(list(code.values()), np.int64)})
        self._table("vocab", {"id": np.array(list(self.ranks.values()), np.int32), "piece": pa.array(list(self.ranks), pa.binary())})
        self.ready_for_long = False

    def _prepare_long(self) -> None:
        """The tables that only the query for long words reads, made when the first such word comes."""
        if self.ready_for_long:
            return
        lefts: dict[int, int] = {}
        rights: dict[int, int] = {}
        for token, r in self.ranks.items():
            for i in range(1, len(token)):
                a, b = self.ranks.get(token[:i]), self.ranks.get(token[i:])
                if a is not None and b is not None:
                    for j in range(1, i):  # what stands there so far is the end of the left part, after byte j - 1
                        if (x := self.ranks.get(token[j:i])) is not None:
                            k = (token[j - 1] << 34) + (x << 17) + b
                            lefts[k] = min(r, lefts.get(k, r))
                    for j in range(i + 1, len(token)):
                        if (y := self.ranks.get(token[i:j])) is not None:
                            k = (a << 25) + (y << 8) + token[j]
                            rights[k] = min(r, rights.get(k, r))
        self._table("lefts", {"k": np.array(list(lefts), np.int64), "m": np.array(list(lefts.values()), np.int32)})
        self._table("rights", {"k": np.array(list(rights), np.int64), "m": np.array(list(rights.values()), np.int32)})
        self.ready_for_long = True

    def _table(self, name: str, cols: dict) -> None:
        self.db.register("given", pa.table(cols))
        self.db.execute(f"create or replace table {name} as select * from given")
        self.db.unregister("given")

    def _read(self, rows: str) -> tuple[np.ndarray, list[pa.Array]]:
        """Words with a token, ascending, and their results."""
        got = self.db.sql(_READ.format(rows=rows)).to_arrow_table().combine_chunks()
        if not len(got):
            return np.zeros(0, np.int64), self.store.empty
        w, ids, parts = (c.chunk(0) for c in got.columns)
        n = np.diff(ids.offsets.to_numpy()).astype(np.int64)
        flat = parts.flatten().cast(pa.large_binary())
        ends = np.concatenate([[0], np.cumsum(run_lengths(flat))])[np.concatenate([[0], np.cumsum(n)])].astype(np.int64)
        back = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(n), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(payload(flat)))])
        return w.to_numpy(), [ragged(ids.flatten().to_numpy().astype(np.int32), n), back]

    def _contract(self, words: list[bytes], query: str) -> list[pa.Array]:
        lengths = np.array([len(x) for x in words])
        flat = np.frombuffer(b"".join(words), np.uint8)
        ends = np.cumsum(lengths)
        self.db.register("word_rows", pa.table({
            "w": np.repeat(np.arange(len(words), dtype=np.int32), lengths),
            "pos": (np.arange(len(flat)) - np.repeat(ends - lengths, lengths)).astype(np.int32),
            "tok": self.byte[flat],
        }))
        _, out = self._read(query)
        self.db.unregister("word_rows")
        return out

    def _learn_words(self, words: list) -> None:
        """Adds each word's results; words are keys of matches of the pattern."""
        whole, short, long = [], [], []
        for k in words:
            x = (" " + k if isinstance(k, str) else k[0]).encode()
            if (r := self.ranks.get(x)) is not None:
                whole.append((k, r, x))
            else:
                (short if len(x) <= LONG else long).append((k, x))
        if whole:
            keys, ids, back = zip(*whole, strict=True)
            self.store.new.add(keys, [ragged(np.array(ids, np.int32), np.ones(len(ids), np.int64)), pa.array(back, pa.large_binary())])
        if long:
            self._prepare_long()
        for at, query in ((short, _CONTRACT), (long, _CONTRACT_LONG)):
            lo = 0
            while lo < len(at):  # a batch is bounded by its words and by its bytes; a longer word stands alone
                hi = lo + 1
                size = len(at[lo][1])
                while hi < len(at) and hi - lo < BATCH and size + len(at[hi][1]) <= BATCH_BYTES:
                    size += len(at[hi][1])
                    hi += 1
                keys, texts_ = zip(*at[lo:hi], strict=True)
                self.store.new.add(keys, self._contract(list(texts_), query))
                lo = hi

    def _learn(self, spans: list) -> None:
        """Adds each stretch's results: those of its matches, end to end; a stretch of one match is that word."""
        find = self.pattern.findall
        several, parts, words = [], [], set()
        for s in spans:
            p = find(" " + s if isinstance(s, str) else s[0])
            if len(p) == 1:
                words.add(s)
            else:
                p = [m[1:] if m[0] == " " and len(m) > 1 else (m,) for m in p]
                several.append(s)
                parts.append(p)
                words.update(p)
        if unknown := self.store.missing(words):
            self._learn_words(unknown)
        if several:
            place = self.store.new.place
            at = np.array([place[m] for p in parts for m in p], np.int64)
            self.store.new.add(several, joined(self.store.new.columns, at, np.fromiter(map(len, parts), np.int64, len(parts))))

    def rest(self) -> None:
        """Gives memory back between tasks; the newer generation stays for the next one."""
        self.store.rest()
        release_memory()

    def keys(self, text: str) -> list:
        """The text's stretches; no match of the pattern crosses their edges.  A plain string stands for itself after one space, a tuple for itself."""
        if not text:
            return []
        if _RUN.search(text):
            return [x[1:] if x[0] == " " and len(x) > 1 else (x,) for x in _STRETCH.findall(text)]
        head, *rest = text.split(" ")
        return [(head,), *rest] if head else rest

    def encode(self, group: list[str]) -> list[pa.Array]:
        """For each text: its ids, and the bytes decoded from them."""
        at, n = of_texts(self.store, [self.keys(x) for x in group], self._learn)
        return joined(self.store.new.columns, at, n)

    def decode(self, ids: list[np.ndarray]) -> list[bytes]:
        """Bytes of each id sequence, by ordered aggregation."""
        out = [b""] * len(ids)
        if not (total := sum(map(len, ids))):
            return out
        lengths = np.array([len(x) for x in ids])
        self.db.register("id_rows", pa.table({"w": np.repeat(np.arange(len(ids), dtype=np.int32), lengths), "pos": np.arange(total, dtype=np.int64), "tok": np.concatenate(ids).astype(np.int32)}))
        at, (_, back) = self._read("from id_rows")
        self.db.unregister("id_rows")
        for w, piece in zip(at.tolist(), back.to_pylist(), strict=True):
            out[w] = piece
        return out

    def as_text(self, ids: pa.Array) -> pa.Array:
        """Decimal ids joined by commas, of each list; each list still ends with a comma."""
        if not hasattr(self, "decimals"):
            self.decimals = pa.array([b"%d," % i for i in range(max(self.ranks.values(), default=0) + 1)], pa.large_binary())
        return joined([self.decimals], payload(ids).astype(np.int64), run_lengths(ids))[0]


def digests(x: pa.Array, drop: int = 0) -> list[str]:
    """Lowercase SHA-256 of each binary value but for its last ``drop`` bytes."""
    data = memoryview(np.ascontiguousarray(payload(x)))
    ends = np.cumsum(run_lengths(x)).tolist()
    return [hashlib.sha256(data[a : max(a, b - drop)]).hexdigest() for a, b in zip([0, *ends], ends)]


@lru_cache(maxsize=2)
def codec(rank_file: str, pattern: str, cache: int = GENERATION) -> Codec:
    return Codec(rank_file, pattern, cache)


def default_vocabulary() -> tuple[str, str]:
    """Rank file and splitting pattern of the production queries; both are parameters of every operator here."""
    import public_tokenizers as P

    return P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN


def encode(df: DataFrame, rank_file: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True, cache: int = GENERATION, keep: bool = True) -> DataFrame:
    """Per document: doc_id, n_tokens, digests of the ids and of the bytes decoded from them, and token_ids on request.

    cache: bytes that each of a worker's two generations of known words may hold.  keep: a worker holds tables and words for its next task; else they
    go with the task, for Spark hands tasks to its idle workers in turn, and all of these would hold them, and texts are taken in smaller steps.
    """

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        gc.disable()  # the caches hold no cycles, and walking them costs more than all else
        c = codec(rank_file, pattern, cache)
        for batch in batches if keep else pieces(batches, "text", STEP_BYTES):
            ids, back = c.encode(texts(batch, "text"))
            out = {"doc_id": batch.column(0), "n_tokens": pa.array(run_lengths(ids)), "ids_sha256": digests(c.as_text(ids), 1), "decoded_sha256": digests(back)}
            if with_ids:
                out["token_ids"] = ids.cast(pa.list_(pa.int32()))
            yield out
            del ids, back, out
            release_memory()
        if keep:
            c.rest()
        else:
            del c
            codec.cache_clear()
            release_memory()

    return map_texts(df, id_col, text_col, kernel, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", token_ids array<int>" * with_ids)


def decode(df: DataFrame, rank_file: str, pattern: str, id_col: str = "doc_id", ids_col: str = "token_ids") -> DataFrame:
    """doc_id and the bytes of an array of ids (null: empty), by one ordered aggregation per batch."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(rank_file, pattern)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                ids = [np.array(x or [], np.int64) for x in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(c.decode(ids), pa.binary())], names=["doc_id", "decoded"])

    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).cast("array<int>").alias("ids")).mapInArrow(run, "doc_id long, decoded binary")
