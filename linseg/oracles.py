"""DuckDB SQL that rebuilds the signals and repeats the methods, for comparison with the Spark queries."""

from __future__ import annotations

USER = """select user_id::varchar signal_id, (row_number() over (partition by user_id order by ts, event_id) - 1)::bigint pos,
  (row_number() over (partition by user_id order by ts, event_id) - 1)::double t, round(value * 100) x0, (props->>'$.k')::double x1 from events"""
SUPPLIER = """select l_suppkey::varchar signal_id, (row_number() over w - 1)::bigint pos, (row_number() over w - 1)::double t,
  l_quantity x0, round(l_extendedprice * 100) x1, round(l_discount * 100) x2, round(l_tax * 100) x3 from lineitem
  window w as (partition by l_suppkey order by l_shipdate, l_orderkey, l_linenumber, l_partkey)"""
HOURLY = """select 'all' signal_id, (row_number() over (order by b) - 1)::bigint pos, (row_number() over (order by b) - 1)::double t, x0, x1, x2, x3, x4 from (
  select date_trunc('hour', ts) b, count(*) filter (event_type = 'click')::double x0, count(*) filter (event_type = 'error')::double x1,
    count(*) filter (event_type = 'purchase')::double x2, count(*) filter (event_type = 'signup')::double x3, count(*) filter (event_type = 'view')::double x4 from events group by 1)"""
BENCHMARK = "select 'all' signal_id, (row_number() over (order by item_id) - 1)::bigint pos, (row_number() over (order by item_id) - 1)::double t, length(text)::double x0 from benchmark"


def draw(*parts: str) -> str:
    """SQL of the md5 uniform; parts are SQL expressions."""
    return "(('0x' || substr(md5(concat_ws('|', " + ", ".join(parts) + ")), 1, 12))::bigint / 281474976710656.0)"


def ends(signal: str, d: int) -> str:
    """CTEs s (the signal) and e: sums over the points before each place 0..N (column e)."""
    sums = ["count(*) over w n", "sum(t) over w st", "sum(t * t) over w stt"]
    for i in range(d):
        sums += [f"sum(x{i}) over w sx{i}", f"sum(t * x{i}) over w stx{i}", f"sum(x{i} * x{i}) over w sxx{i}"]
    zeros = ", ".join(["0::double"] * (3 + 3 * d))
    return f"""s as materialized ({signal}),
e as materialized (
  select signal_id, pos + 1 e, {", ".join(sums)} from s window w as (partition by signal_id order by pos rows unbounded preceding)
  union all select distinct signal_id, 0, {zeros} from s),
size as materialized (select signal_id, max(e) n from e group by 1)"""


def cost(a: str, b: str, d: int, sloped: bool = True) -> str:
    """Squared error of the range between two rows of e."""
    m = lambda c: f"({b}.{c} - {a}.{c})"
    parts = []
    for i in range(d):
        flat = f"{m(f'sxx{i}')} - {m(f'sx{i}')} * {m(f'sx{i}')} / {m('n')}"
        if sloped:
            cov, var = f"({m(f'stx{i}')} - {m('st')} * {m(f'sx{i}')} / {m('n')})", f"({m('stt')} - {m('st')} * {m('st')} / {m('n')})"
            flat = f"case when {m('n')} > 2 then {flat} - {cov} * {cov} / {var} else 0 end"
        parts.append(f"({flat})")
    whole = f"greatest({' + '.join(parts)}, 0)"
    return whole if sloped else f"case when {m('n')} > 1 then {whole} else 0 end"


def slope(a: str, b: str, i: int) -> str:
    m = lambda c: f"({b}.{c} - {a}.{c})"
    return f"case when {m('n')} > 1 then ({m(f'stx{i}')} - {m('st')} * {m(f'sx{i}')} / {m('n')}) / ({m('stt')} - {m('st')} * {m('st')} / {m('n')}) else 0 end"


def planted(signal: str, scale: tuple, k: int, seed: str, amp: float, nz: float) -> str:
    """CTEs base, truth and planted (a signal) without curves."""
    d = len(scale)
    q = f"'{seed}'"
    cut = lambda j: f"case when {j} = 0 then 0 when {j} = k then n else floor(n * ({j} + 0.5 * ({draw(q, 'signal_id', f'({j})::varchar', repr('cut'))} - 0.5)) / k)::bigint end"
    level = lambda r: f"(case when seg_no % 2 = 0 then 1.0 else -1.0 end) * {amp} * (0.5 + {draw(q, 'signal_id', 'seg_no::varchar', repr(str(r)), repr('level'))})"
    tilt = lambda r: f"2 * {amp} * ({draw(q, 'signal_id', 'seg_no::varchar', repr(str(r)), repr('slope'))} - 0.5)"
    value = lambda r, m, sd: f"{nz} * ((x{r} - {m!r}) / {sd!r}) + {level(r)} + {tilt(r)} * ((pos - start_pos) / n) x{r}"
    return f"""base as materialized ({signal}),
truth as materialized (
  select signal_id, seg_no::int seg_no, ({cut("seg_no")})::bigint start_pos, ({cut("seg_no + 1")})::bigint end_pos, n
  from (select signal_id, n, {k} k, unnest(range({k})) seg_no from (select signal_id, count(*) n from base group by 1))),
planted as materialized (
  select signal_id, pos, t, {", ".join(value(r, m, sd) for r, (m, sd) in enumerate(scale))}
  from (select base.*, seg_no, start_pos, n from base join truth on truth.signal_id = base.signal_id and pos >= start_pos and pos < end_pos))"""


def best_cut(d: int, gamma: int = 2) -> str:
    """CTE best over e: the exact two-piece model of each signal."""
    return f"""best as materialized (
  select signal_id, b.cut cut, b.cost cost, whole from (
    select l.signal_id, min({{'cost': {cost("o", "l", d)} + {cost("l", "h", d)}, 'cut': l.e}}) b, min({cost("o", "h", d)}) whole
    from e l join size z on z.signal_id = l.signal_id join e o on o.signal_id = l.signal_id and o.e = 0 join e h on h.signal_id = l.signal_id and h.e = z.n
    where l.e >= {gamma} and l.e <= z.n - {gamma} group by 1))"""


def binary_split(signal: str, d: int, k: int, gamma: int = 2) -> str:
    return f"""with recursive {ends(signal, d)},
state(step, signal_id, cuts) as (
  select 1, signal_id, [0::bigint, n::bigint] from size
  union all (
  with p as (select signal_id, step, cuts, unnest(range(1, len(cuts)::bigint)) i from state where step < {k}),
  c as (
    select p.signal_id, o.e lo, min({{'cost': {cost("o", "l", d)} + {cost("l", "h", d)}, 'cut': l.e}}) b, min({cost("o", "h", d)}) whole
    from p join e o on o.signal_id = p.signal_id and o.e = p.cuts[p.i] join e h on h.signal_id = p.signal_id and h.e = p.cuts[p.i + 1]
    join e l on l.signal_id = p.signal_id and l.e >= o.e + {gamma} and l.e <= h.e - {gamma} group by 1, 2),
  t as (select signal_id, max({{'gain': whole - b.cost, 'left': -lo, 'cut': b.cut}}) b from c group by 1)
  select step + 1, signal_id, list_sort(list_append(cuts, b.cut::bigint)) from state join t using (signal_id) where step < {k}))
select signal_id, unnest(cuts[2:len(cuts) - 1])::bigint cut from state qualify step = max(step) over (partition by signal_id)"""


def layers(signal: str, d: int, k: int, gamma: int = 2) -> str:
    """CTEs l1..lk: least cost with j pieces up to each place, with the place before (the smallest of equal ones)."""
    out = [ends(signal, d), f"c as materialized (select a.signal_id, a.e i, b.e j, {cost('a', 'b', d)} cost from e a join e b on a.signal_id = b.signal_id and b.e >= a.e + {gamma})", "l1 as materialized (select signal_id, j, cost, 0::bigint i from c where i = 0)"]
    for n in range(2, k + 1):
        out.append(f"l{n} as materialized (select signal_id, j, b.cost cost, b.i i from (select c.signal_id, c.j, min({{'cost': p.cost + c.cost, 'i': c.i}}) b from c join l{n - 1} p on p.signal_id = c.signal_id and p.j = c.i group by 1, 2))")
    return "with " + ",\n".join(out)


def merge_path(signal: str, d: int, delta: int, k: int) -> str:
    """Recursive CTE m(step, signal_id, edges, cut, gain): strict greedy merging of even cells."""
    return f"""with recursive {ends(signal, d)},
m(step, signal_id, edges, cut, gain) as (
  select 0, signal_id, list_transform(range(greatest(1, n // {delta})::bigint + 1), lambda i: (i * n) // greatest(1, n // {delta}))::bigint[], null::bigint, null::double from size
  union all (
  with p as (select step, signal_id, edges, unnest(range(2, len(edges)::bigint)) i from m where len(edges) - 1 > {k}),
  g as (
    select p.signal_id, min({{'gain': {cost("a", "b", d)} - {cost("a", "o", d)} - {cost("o", "b", d)}, 'cut': o.e}}) b
    from p join e a on a.signal_id = p.signal_id and a.e = p.edges[p.i - 1] join e o on o.signal_id = p.signal_id and o.e = p.edges[p.i] join e b on b.signal_id = p.signal_id and b.e = p.edges[p.i + 1]
    group by 1)
  select step + 1, m.signal_id, list_filter(edges, lambda v: v <> g.b.cut), g.b.cut::bigint, g.b.gain from m join g using (signal_id) where len(edges) - 1 > {k}))"""


def refinement(signal: str, d: int, k: int, starts: str, gamma: int = 2, tol: float = 1e-4, sweeps: int = 100, shuffled: bool = False) -> str:
    """Recursive CTE r(sweep, signal_id, run, c1.., cost, stop) for two or three pieces, cuts visited from left to right or, of two, in drawn order.

    ``starts``: a query giving signal_id, run, c1..; the running error difference is a combination of the sums in e.
    """
    cuts = [f"c{j}" for j in range(1, k)]
    sums = ["n", "st", "stt", *[f"{c}{i}" for i in range(d) for c in ("sx", "stx", "sxx")]]
    place = lambda j: "0" if j == 0 else ("n" if j == k else f"c{j}")
    found = ", ".join(f"v[({place(j)})::bigint + 1] o{j}" for j in range(k + 1))
    total = " + ".join(cost(f"o{j}", f"o{j + 1}", d) for j in range(k))

    def diff(j: int, lo: str, p: str) -> str:
        """Running difference of errors of line j and j+1 over [lo, p)."""
        m = lambda c: f"({p}.{c} - {lo}.{c})"
        out = []
        for i in range(d):
            a, b, c, f = f"i{j}_{i}", f"m{j}_{i}", f"i{j + 1}_{i}", f"m{j + 1}_{i}"
            out.append(f"-2 * (({a} - {c}) * {m(f'sx{i}')} + ({b} - {f}) * {m(f'stx{i}')}) + ({a} * {a} - {c} * {c}) * {m('n')} + 2 * ({a} * {b} - {c} * {f}) * {m('st')} + ({b} * {b} - {f} * {f}) * {m('stt')}")
        return " + ".join(out)

    fields = []
    for j in range(k):
        for i in range(d):
            s = slope(f"o{j}", f"o{j + 1}", i)
            fields += [f"{s} m{j}_{i}", f"((o{j + 1}.sx{i} - o{j}.sx{i}) - ({s}) * (o{j + 1}.st - o{j}.st)) / (o{j + 1}.n - o{j}.n) i{j}_{i}"]
    steps, last = [], "f"
    for j in range(1, k):
        lo = "0" if j == 1 else f"cut{j - 1}"
        steps.append(f"""v{j} as materialized (
    select any_value(columns({last}.* exclude (signal_id, run))), {last}.signal_id, {last}.run, min({{'d': {diff(j - 1, f"{last}.v[({lo})::bigint + 1]", "p")}, 'cut': p.e}}).cut cut{j}
    from {last} join e p on p.signal_id = {last}.signal_id and p.e >= {lo} + {gamma} and p.e <= {"n0" if j == k - 1 else f"c{j + 1}"} - {gamma} group by {last}.signal_id, {last}.run)""")
        last = f"v{j}"
    if shuffled and k == 3:
        at = lambda row, c: f"{row}.v[({c})::bigint + 1]"
        turn = lambda row, first, second: f"case when {row}.cut_first = 1 then {first} else {second} end"
        steps = [
            f"""v1 as materialized (
    select any_value(columns(f.* exclude (signal_id, run))), f.signal_id, f.run, min({{'d': {turn("f", diff(0, at("f", "0"), "p"), diff(1, at("f", "f.c1"), "p"))}, 'cut': p.e}}).cut got1
    from f join e p on p.signal_id = f.signal_id and p.e >= {turn("f", "0", "f.c1")} + {gamma} and p.e <= {turn("f", "f.c2", "f.n0")} - {gamma} group by f.signal_id, f.run)""",
            f"""v2 as materialized (
    select any_value(columns(v1.* exclude (signal_id, run))), v1.signal_id, v1.run, min({{'d': {turn("v1", diff(1, at("v1", "v1.got1"), "p"), diff(0, at("v1", "0"), "p"))}, 'cut': p.e}}).cut got2
    from v1 join e p on p.signal_id = v1.signal_id and p.e >= {turn("v1", "v1.got1", "0")} + {gamma} and p.e <= {turn("v1", "v1.n0", "v1.got1")} - {gamma} group by v1.signal_id, v1.run)""",
        ]
        last = "v2"
        fields.append("case when " + draw("'0'", "signal_id", "'order'", "sweep::varchar", "'0'") + " <= " + draw("'0'", "signal_id", "'order'", "sweep::varchar", "'1'") + " then 1 else 2 end cut_first")
    new = "case when cut_first = 1 then got1 else got2 end c1, case when cut_first = 1 then got2 else got1 end c2" if shuffled and k == 3 else ", ".join(f"cut{j} c{j}" for j in range(1, k))
    held = ", ".join(cuts)
    return f"""with recursive {ends(signal, d)},
el as materialized (select signal_id, list({{{", ".join(f"'{c}': {c}" for c in sums)}}} order by e) v from e group by 1),
start as (select b.signal_id, b.run, {", ".join("b." + c for c in cuts)}, z.n::bigint n, v from ({starts}) b join size z using (signal_id) join el using (signal_id)),
r(sweep, signal_id, run, n, {held}, cost, before) as (
  select 0, signal_id, run, n, {held}, {total}, null::double from (select *, {found} from start)
  union all (
  with f as materialized (
    select sweep, signal_id, run, n n0, {held}, cost, v, {", ".join(fields)}
    from (select r.*, v, {found} from r join el using (signal_id) where sweep < {sweeps} and (before is null or before - cost > {tol} * before))),
  {", ".join(steps)},
  w as (select sweep + 1 sweep, signal_id, run, n0 n, {new}, cost before, v from {last})
  select sweep, signal_id, run, n, {held}, {total}, before from (select *, {found} from w)))"""


def bicriteria(d: int, k: int, gamma: int = 2) -> str:
    """Recursive CTE b over e (round, signal_id, lo, hi, cost, banked), and scale."""
    return f"""b(round, signal_id, lo, hi, cost, banked) as (
  select 0, signal_id, 0::bigint, n::bigint, null::double, false from size
  union all (
  with z as (select *, greatest({gamma}, (sum(hi - lo) over (partition by signal_id) + {4 * k - 1}) // {4 * k})::bigint part from b where not banked),
  p as (select round, signal_id, part, lo + i * part lo, least(lo + (i + 1) * part, hi) hi from (select *, unnest(range((hi - lo + part - 1) // part)) i from z)),
  c as (select p.*, {cost("x", "y", d)} cost from p join e x on x.signal_id = p.signal_id and x.e = lo join e y on y.signal_id = p.signal_id and y.e = hi),
  o as (select *, row_number() over (partition by signal_id order by cost, lo) nth, count(*) over (partition by signal_id) m from c)
  select round + 1, signal_id, lo, hi, cost, nth <= case when part <= {gamma} or m <= {2 * k} then m else (m + 1) // 2 end from o)),
scale as materialized (select signal_id, sum(cost) scale from b where banked group by 1)"""


def over_cells(signal: str, d: int, factor: str, gamma: int = 2) -> str:
    """``with recursive`` up to top(signal_id, n_cells, c1, c2, cost): dynamic programming over balanced cells, three pieces.  factor: SQL over size's n."""
    return f"""with recursive {ends(signal, d)}, {bicriteria(d, 3, gamma)},
budget as materialized (select z.signal_id, z.n::bigint n, greatest(scale / (3 * ({factor})), 1e-12 * (select {" + ".join(f"x.sxx{i} - x.sx{i} * x.sx{i} / x.n" for i in range(d))} from e x where x.signal_id = z.signal_id and x.e = z.n)) budget from size z join scale using (signal_id)),
g(cell, signal_id, lo, hi) as (
  select -1, signal_id, 0::bigint, 0::bigint from budget union all
  select cell + 1, g.signal_id, g.hi, max(y.e)::bigint from g join budget w using (signal_id) join e x on x.signal_id = g.signal_id and x.e = g.hi join e y on y.signal_id = g.signal_id and y.e > g.hi
  where g.hi < w.n and (y.e <= g.hi + 2 or {cost("x", "y", d)} <= w.budget) group by 1, 2, 3),
edge as materialized (select signal_id, hi place from g),
cells as (select signal_id, count(*) - 1 n_cells from edge group by 1),
c as materialized (select x.signal_id, x.e i, y.e j, {cost("x", "y", d)} cost from edge p join edge q on q.signal_id = p.signal_id and q.place >= p.place + {gamma} join e x on x.signal_id = p.signal_id and x.e = p.place join e y on y.signal_id = q.signal_id and y.e = q.place),
l1 as (select signal_id, j, cost, 0::bigint i from c where i = 0),
l2 as materialized (select signal_id, j, b.cost cost, b.i i from (select c.signal_id, c.j, min({{'cost': p.cost + c.cost, 'i': c.i}}) b from c join l1 p on p.signal_id = c.signal_id and p.j = c.i group by 1, 2)),
l3 as (select signal_id, j, b.cost cost, b.i i from (select c.signal_id, c.j, min({{'cost': p.cost + c.cost, 'i': c.i}}) b from c join l2 p on p.signal_id = c.signal_id and p.j = c.i group by 1, 2)),
top as materialized (select z.signal_id, n_cells, l2.i::bigint c1, l3.i::bigint c2, l3.cost cost from size z join cells using (signal_id) join l3 on l3.signal_id = z.signal_id and l3.j = z.n join l2 on l2.signal_id = z.signal_id and l2.j = l3.i)"""


def windowed_cuts(window: int, mode: str, threshold: float) -> str:
    """Cuts of each user's events by the windowed two-piece test: signal_id, cut_us, gain, window_n."""
    signal = "select user_id::varchar signal_id, (row_number() over w - 1)::bigint pos, (epoch_us(ts) - min(epoch_us(ts)) over (partition by user_id)) / 1e6 t, round(value * 100) x0 from events window w as (partition by user_id order by ts, round(value * 100))"
    inner = f"l.e = m.lo + {window // 2}" if mode == "half" else f"l.e >= m.lo + 2 and l.e <= m.lo + {window - 2}"
    return f"""with recursive {ends(signal, 1)}, us as (select user_id::varchar signal_id, row_number() over (partition by user_id order by ts, round(value * 100)) - 1 pos, epoch_us(ts) us from events),
m(lo, signal_id, cut, gain) as (
  select 0::bigint, signal_id, null::bigint, null::double from size
  union all (
  with f as (
    select m.signal_id, m.lo, min({{'cost': {cost("x", "l", 1)} + {cost("l", "y", 1)}, 'cut': l.e}}) b, min({cost("x", "y", 1)}) whole
    from m join e x on x.signal_id = m.signal_id and x.e = m.lo join e y on y.signal_id = m.signal_id and y.e = m.lo + {window} join e l on l.signal_id = m.signal_id and {inner} group by 1, 2),
  h as (select *, whole > 0 and (whole - b.cost) / whole >= {threshold} hit from f)
  select case when hit then b.cut else lo + {window // 2} end::bigint, signal_id, case when hit then b.cut end::bigint, case when hit then (whole - b.cost) / whole end from h))
select m.signal_id, us.us::bigint cut_us, round(gain, 6) gain from m join us on us.signal_id = m.signal_id and us.pos = m.cut"""
