"""Mixing sources to target weights by iterative proportional fitting.

Documents fall into cells of source, language and topic.  Raking scales the cells' token weights in turn until each
marginal has its target share of the token budget; no name and no cell is asked for more tokens than it has: what a name
can't give, the dimension's other names take over in proportion to their targets.  A cell's calibrated
probability is its raked weight over its tokens, and a document stays where a hash of its id falls below that.

Defined results: a null source or language is the name '(none)'; a null text has no tokens; a cell without tokens has
probability 0; repeated rows share their id's fate; an empty table gives no rows; a name without target gets none; texts of
any length are counted whole; a hash equal to the probability is not kept; columns of ``df`` keep their names and values
whatever they are called.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, cut, fresh, unit_hash

DIMS = ("source", "lang", "topic")
#: Rounds of raking; the share of all tokens that is asked for; the power that tempers observed shares to targets.
ROUNDS, BUDGET, TEMPER = 60, 0.6, 0.7
SEED = "mix-1"
#: Cells that are raked on the driver (some tens of bytes each) and broadcast; more are raked as a table.
DRIVER_CELLS = 200_000


def words_of(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def topic_of(text: Column, words: Column) -> Column:
    """A topic by shape, from counts alone."""
    bars = F.length(text) - F.length(F.replace(text, F.lit("|"), F.lit("")))
    marks = F.length(text) - F.length(F.translate(text, "#*$%&<>", ""))
    return F.when(20 * bars > words, "tabular").when(20 * marks > words, "markup").when(words < 100, "brief").when(words < 1000, "article").otherwise("long_form")


def described(df: DataFrame, text_col: str = "text", source: str = "source", lang: str = "lang", name: str = "__mix") -> DataFrame:
    """The rows with a struct ``name`` (a column that ``df`` doesn't have) of source, lang, topic and tokens."""
    text = F.coalesce(F.col(f"`{text_col}`"), F.lit(""))
    words = words_of(text)
    named = lambda c: F.coalesce(F.col(f"`{c}`").cast("string"), F.lit("(none)"))
    return df.withColumn(name, F.struct(named(source).alias("source"), named(lang).alias("lang"), topic_of(text, words).alias("topic"), words.alias("tokens")))


def tempered(shares: dict[str, float], power: float = TEMPER) -> dict[str, float]:
    total = sum(v**power for v in shares.values() if v > 0)
    return {k: (v**power / total if v > 0 else 0.0) for k, v in shares.items()}


def reachable(target: np.ndarray, tokens: np.ndarray) -> np.ndarray:
    """Targets of one dimension's names, none above the tokens at hand; what those can't take goes to the others in proportion."""
    out, whole = np.zeros_like(target), target.sum()
    order = np.argsort(np.divide(tokens, target, out=np.full_like(target, np.inf), where=target > 0), kind="stable")
    t, w = tokens[order], target[order]
    left = whole - (np.cumsum(t) - t)  # before each name, when all names before it are full
    rest = np.cumsum(w[::-1])[::-1]
    full = np.divide(left, rest, out=np.zeros_like(w), where=rest > 0) * w >= t
    full = np.cumprod(full).astype(bool) & (w > 0)
    spare, weight = whole - t[full].sum(), w[~full].sum()
    out[order] = np.where(full, t, w * (spare / weight if weight > 0 else 0.0))
    return out


def rake(tokens: np.ndarray, codes: list[np.ndarray], targets: list[np.ndarray], budget: float, rounds: int = ROUNDS) -> np.ndarray:
    """Raked tokens of each cell: codes and targets (tokens) of each dimension; ends early once a round changes nothing."""
    m = tokens * budget
    targets = [reachable(t, np.bincount(c, tokens, len(t))) for c, t in zip(codes, targets, strict=True)]
    for _ in range(rounds):
        before = m
        for code, target in zip(codes, targets, strict=True):
            have = np.bincount(code, m, len(target))
            m = m * np.divide(target, have, out=np.zeros_like(target), where=have > 0)[code]
        m = np.minimum(m, tokens)
        if np.abs(m - before).max(initial=0.0) <= 1e-13 * tokens.sum():
            break
    return m


def residual(tokens: np.ndarray, codes: list[np.ndarray], targets: list[np.ndarray], m: np.ndarray) -> float:
    """Largest distance of a marginal from its reachable target, as a share of all raked tokens."""
    off = [np.abs(np.bincount(c, m, len(t)) - reachable(t, np.bincount(c, tokens, len(t)))).max(initial=0.0) for c, t in zip(codes, targets, strict=True)]
    return float(max(off, default=0.0) / max(m.sum(), 1.0))


def _reachable_table(cells: DataFrame, targets: DataFrame, d: str) -> DataFrame:
    """``reachable`` for names in any number (d, target); the running sums go over one row a name."""
    at = targets.join(cells.groupBy(d).agg(F.sum("tokens").cast("double").alias("have")), d).where("target > 0")
    whole = targets.agg(F.coalesce(F.sum("target"), F.lit(0.0))).first()[0]
    up = Window.orderBy(F.col("have") / F.col("target"), d)
    at = at.withColumn("before", F.sum("have").over(up.rowsBetween(Window.unboundedPreceding, 0)) - F.col("have")).withColumn("rest", F.sum("target").over(up.rowsBetween(0, Window.unboundedFollowing)))
    at = cut(at.withColumn("full", (whole - F.col("before")) / F.col("rest") * F.col("target") >= F.col("have")))  # full names come first
    took, weight = at.agg(F.coalesce(F.sum(F.when(F.col("full"), F.col("have"))), F.lit(0.0)), F.coalesce(F.sum(F.when(~F.col("full"), F.col("target"))), F.lit(0.0))).first()
    return at.select(d, F.when(F.col("full"), F.col("have")).otherwise(F.col("target") * ((whole - took) / weight if weight else 0.0)).alias("target"))


def _rake_table(cells: DataFrame, targets: dict[str, DataFrame], budget: float, rounds: int) -> DataFrame:
    """The same for cells in any number: sums by name, summed in the tasks first, and joins with them; checkpointed every few rounds."""
    m = cells.withColumn("m", F.col("tokens") * budget)
    for d, t in targets.items():
        m = m.join(_reachable_table(cells, t, d).select(d, F.col("target").alias(f"to_{d}")), d, "left").fillna(0.0, [f"to_{d}"])
    for r in range(rounds):
        for d in targets:
            have = m.groupBy(d).agg(F.sum("m").alias("have"))
            m = m.join(have, d).withColumn("m", F.when(F.col("have") > 0, F.col("m") * F.col(f"to_{d}") / F.col("have")).otherwise(0.0)).drop("have")
        m = cut(m.withColumn("m", F.least("m", F.col("tokens").cast("double"))))
    return m.select(*DIMS, "tokens", "m")


def probabilities(df: DataFrame, targets: dict[str, dict[str, float]] | None = None, budget: float = BUDGET, rounds: int = ROUNDS, driver_cells: int = DRIVER_CELLS, name: str = "__mix") -> DataFrame:
    """source, lang, topic, probability of each cell of described rows.

    ``targets``: shares by name for each dimension that is constrained; None tempers all three observed marginals.
    """
    spark = df.sparkSession
    cells = cut(df.groupBy(*[F.col(f"{name}.{d}").alias(d) for d in DIMS]).agg(F.sum(f"{name}.tokens").alias("tokens")))
    n = cells.count()
    if n <= driver_cells:
        rows = sorted(cells.collect(), key=lambda r: tuple(r[d] for d in DIMS))
        tokens = np.array([r.tokens for r in rows], float)
        total = tokens.sum()
        codes, goals = [], []
        for d in DIMS:
            names = {x: i for i, x in enumerate(sorted({r[d] for r in rows}))}
            code = np.array([names[r[d]] for r in rows], int)
            if targets is None:
                share = tempered(dict(zip(names, np.bincount(code, tokens, len(names)) / max(total, 1.0), strict=True)))
            elif d in targets:
                share = targets[d]
            else:
                continue
            codes.append(code)
            goals.append(np.array([share.get(x, 0.0) for x in names]) * total * budget)
        m = rake(tokens, codes, goals, budget, rounds)
        p = np.divide(m, tokens, out=np.zeros_like(m), where=tokens > 0)
        return spark.createDataFrame([(*(r[d] for d in DIMS), float(x)) for r, x in zip(rows, p, strict=True)], "source string, lang string, topic string, probability double")
    total = cells.agg(F.sum("tokens")).first()[0] or 0
    given = {}
    for d in DIMS:
        if targets is None:
            by = cells.groupBy(d).agg((F.pow(F.sum("tokens") / max(total, 1), F.lit(TEMPER))).alias("s"))
            whole = by.agg(F.sum("s")).first()[0]
            given[d] = by.select(d, (F.col("s") / whole * total * budget).alias("target"))
        elif d in targets:
            given[d] = spark.createDataFrame([(k, float(v) * total * budget) for k, v in targets[d].items()], f"{d} string, target double")
    raked = _rake_table(cells, given, budget, rounds)
    return raked.select(*DIMS, F.when(F.col("tokens") > 0, F.col("m") / F.col("tokens")).otherwise(0.0).alias("probability"))


def _decided(df: DataFrame, p: DataFrame, id_col: Column, seed: str, driver_cells: int, name: str, out: tuple[str, str]) -> DataFrame:
    """With the probability and the decision under the names ``out``; the cell table is broadcast only when its count allows."""
    cell, chance = fresh(df, "__cell"), out[0]
    p = p.select(F.struct(*DIMS).alias(cell), F.col("probability").alias(chance))
    few = p.limit(driver_cells + 1).count() <= driver_cells
    joined = df.join(F.broadcast(p) if few else p, F.struct(*[F.col(f"{name}.{d}").alias(d) for d in DIMS]) == F.col(cell), "left")
    return joined.withColumn(out[1], unit_hash(seed, F.coalesce(id_col.cast("string"), F.lit(""))) < F.coalesce(chance, F.lit(0.0)))


def mix(df: DataFrame, targets: dict[str, dict[str, float]] | None = None, budget: float = BUDGET, seed: str = SEED, id_col: str = "doc_id", driver_cells: int = DRIVER_CELLS, text_col: str = "text", source: str = "source", lang: str = "lang") -> DataFrame:
    """Per row: doc_id, source, lang, topic, n_tokens, probability, kept."""
    rows = df.select(*[F.col(f"`{c}`").cast(t).alias(n) for c, t, n in ((id_col, "long", "doc_id"), (text_col, "string", "text"), (source, "string", "source"), (lang, "string", "lang"))])
    rows = described(rows).select("doc_id", "__mix")
    out = _decided(rows, probabilities(rows, targets, budget, driver_cells=driver_cells), F.col("doc_id"), seed, driver_cells, "__mix", ("__p", "__kept"))
    return out.select("doc_id", *[F.col(f"__mix.{d}").alias(d) for d in DIMS], F.col("__mix.tokens").alias("n_tokens"), F.round("__p", 9).alias("probability"), F.col("__kept").alias("kept"))


def sample(df: DataFrame, targets: dict[str, dict[str, float]] | None = None, budget: float = BUDGET, seed: str = SEED, id_col: str = "doc_id", text_col: str = "text", source: str = "source", lang: str = "lang") -> DataFrame:
    """The sampled rows, all columns unchanged, whatever their names."""
    name, out = fresh(df, "__mix"), (fresh(df, "__p"), fresh(df, "__kept"))
    rows = described(df, text_col, source, lang, name)
    picked = _decided(rows, probabilities(rows, targets, budget, name=name), F.col(f"`{id_col}`"), seed, DRIVER_CELLS, name, out)
    return picked.where(F.col(out[1])).select(*[F.col(f"`{c}`") for c in df.columns])


def achieved(mixed: DataFrame) -> DataFrame:
    """Marginal report of a mix: dimension, name, tokens at hand, expected and kept."""
    parts = [
        mixed.groupBy(F.lit(d).alias("dimension"), F.col(d).alias("name")).agg(
            F.sum("n_tokens").alias("tokens"), F.sum(F.col("n_tokens") * F.col("probability")).alias("expected"), F.sum(F.when(F.col("kept"), F.col("n_tokens")).otherwise(0)).alias("kept")
        )
        for d in DIMS
    ]
    return reduce(DataFrame.unionByName, parts)


def oracle() -> str:
    """DuckDB SQL for ``mix`` with its defaults."""
    inner = "(select * from rounds where i < " + str(ROUNDS) + ")"
    for d in DIMS:
        inner = f"(select i, source, lang, topic, tokens, to_source, to_lang, to_topic, case when have > 0 then m * to_{d} / have else 0.0 end m from (select *, sum(m) over (partition by {d}) have from {inner}))"
    whole = f"(select sum(tokens) from cells) * {BUDGET}"

    def goal(d: str) -> str:
        return f"""w_{d} as (select {d}, tokens have, pow(tokens, {TEMPER}) / sum(pow(tokens, {TEMPER})) over () * {whole} want from (select {d}, sum(tokens) tokens from cells group by 1) where tokens > 0),
u_{d} as (select {d}, have, want, ({whole} - (sum(have) over (order by have / want, {d}) - have)) / sum(want) over (order by have / want desc, {d} desc) * want >= have full_ from w_{d}),
t_{d} as (select {d}, case when full_ then have else want * ({whole} - coalesce((select sum(have) from u_{d} where full_), 0)) / (select sum(want) from u_{d} where not full_) end g from u_{d}
  union all select {d}, 0.0 from cells group by 1 having sum(tokens) = 0)"""

    return f"""
with recursive words as (
  select doc_id, coalesce(source, '(none)') source, coalesce(lang, '(none)') lang, coalesce(text, '') txt,
    len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::bigint n_tokens from documents),
docs as (
  select doc_id, source, lang, n_tokens, case
    when 20 * (length(txt) - length(replace(txt, '|', ''))) > n_tokens then 'tabular'
    when 20 * (length(txt) - length(translate(txt, '#*$%&<>', ''))) > n_tokens then 'markup'
    when n_tokens < 100 then 'brief' when n_tokens < 1000 then 'article' else 'long_form' end topic from words),
cells as (select source, lang, topic, sum(n_tokens)::double tokens from docs group by all),
{", ".join(goal(d) for d in DIMS)},
rounds as (
  select 0 i, source, lang, topic, tokens, a.g to_source, b.g to_lang, c.g to_topic, tokens * {BUDGET} m
  from cells join t_source a using (source) join t_lang b using (lang) join t_topic c using (topic)
  union all
  select i + 1, source, lang, topic, tokens, to_source, to_lang, to_topic, least(m, tokens) from {inner}),
p as (select source, lang, topic, case when tokens > 0 then m / tokens else 0.0 end p from rounds where i = {ROUNDS})
select doc_id, source, lang, topic, n_tokens, round(p, 9) probability,
  ('0x' || substr(md5('{SEED}|' || coalesce(doc_id::varchar, '')), 1, 12))::bigint / 281474976710656.0 < p kept
from docs join p using (source, lang, topic)
"""
