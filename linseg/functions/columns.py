"""Column expressions: vectors, times, texts, and the linear-fit formulas on sums."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def vadd(a, b) -> Column:
    return F.zip_with(a, b, lambda p, q: p + q)


def vsub(a, b) -> Column:
    return F.zip_with(a, b, lambda p, q: p - q)


def vscale(a, s) -> Column:
    return F.transform(a, lambda p: p * s)


def vdot(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)


def vnorm2(a) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + v * v)


def sq_dist(a, b) -> Column:
    return vnorm2(vsub(a, b))


def line_value(intercept, slope, t) -> Column:
    return F.zip_with(intercept, slope, lambda c, m: c + m * t)


def bucket_time(ts, every: str) -> Column:
    return F.date_trunc(every, ts)


def to_event_time(ts) -> Column:
    """Zone-free time stamps to what watermarks accept."""
    return F.col(ts).cast("timestamp") if isinstance(ts, str) else ts.cast("timestamp")


def micros(ts) -> Column:
    return F.unix_micros(to_event_time(ts))


def json_number(col, key: str) -> Column:
    return F.get_json_object(col, f"$.{key}").cast("double")


def map_to_vector(col, keys: list[str]) -> Column:
    return F.array(*[F.coalesce(F.element_at(col, k), F.lit(0.0)).cast("double") for k in keys])


def text_features(col) -> Column:
    """Characters, words, lines, share of letters."""
    c = F.coalesce(col, F.lit(""))
    n = F.length(c)
    return F.array(n.cast("double"), F.regexp_count(c, F.lit(r"\S+")).cast("double"), (n - F.length(F.replace(c, F.lit("\n"), F.lit(""))) + 1).cast("double"), F.when(n > 0, F.regexp_count(c, F.lit("[A-Za-z]")) / n).otherwise(0.0))


def unit_hash(*cols) -> Column:
    """Uniform in [0, 1) from md5 of the values joined by '|'."""
    joined = F.concat_ws("|", *[F.lit(c) if isinstance(c, (str, int)) else c.cast("string") for c in cols])
    return F.conv(F.substring(F.md5(joined), 1, 12), 16, 10).cast("double") / F.lit(float(1 << 48))


#: Names of the sums that a range of a d-dimensional signal has.
def sum_names(d: int) -> list[str]:
    return ["n", "st", "stt", *[f"{s}{i}" for i in range(d) for s in ("sx", "stx", "sxx")]]


def sum_terms(d: int, t="t", x="x") -> dict[str, Column]:
    t = F.col(t) if isinstance(t, str) else t
    out = {"n": F.lit(1.0), "st": t, "stt": t * t}
    for i in range(d):
        v = F.col(x)[i]
        out |= {f"sx{i}": v, f"stx{i}": t * v, f"sxx{i}": v * v}
    return out


def line_cost(m, d: int, sloped: bool = True) -> Column:
    """Squared error of the best line from sums; ``m(name)`` gives a sum's column."""
    n, st, stt = m("n"), m("st"), m("stt")
    parts = []
    for i in range(d):
        sx, stx, sxx = m(f"sx{i}"), m(f"stx{i}"), m(f"sxx{i}")
        flat = sxx - sx * sx / n
        if sloped:
            cov, var = stx - st * sx / n, stt - st * st / n
            flat = F.when(n > 2, flat - cov * cov / var).otherwise(F.lit(0.0))
        parts.append(flat)
    whole = reduce(lambda a, b: a + b, parts)
    return F.greatest(whole, F.lit(0.0)) if sloped else F.when(n > 1, F.greatest(whole, F.lit(0.0))).otherwise(F.lit(0.0))


def slope_of(m, i: int) -> Column:
    n, st, stt, sx, stx = m("n"), m("st"), m("stt"), m(f"sx{i}"), m(f"stx{i}")
    return F.when(n > 1, (stx - st * sx / n) / (stt - st * st / n)).otherwise(F.lit(0.0))


def intercept_of(m, i: int) -> Column:
    return (m(f"sx{i}") - slope_of(m, i) * m("st")) / m("n")


def given_line_cost(m, d: int, intercept: list[Column], slope: list[Column]) -> Column:
    """Squared error of any line from sums (not the best one)."""
    n, st, stt = m("n"), m("st"), m("stt")
    parts = [m(f"sxx{i}") - 2 * (c * m(f"sx{i}") + s * m(f"stx{i}")) + n * c * c + 2 * c * s * st + s * s * stt for i, (c, s) in enumerate(zip(intercept, slope, strict=True))]
    return reduce(lambda a, b: a + b, parts)
