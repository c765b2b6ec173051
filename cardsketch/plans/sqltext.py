"""SQL twins of the queries, for DuckDB, over the portable hash."""

from __future__ import annotations

from ..functions.constants import LOGLOG, PHI, alpha, gamma, variance


def lit(x: float) -> str:
    return f"cast('{x!r}' as double)"


def _list(by: list[str], tail: str = ", ") -> str:
    return "".join(f"{c}{tail}" for c in by)


def composite(*parts: str) -> str:
    """The text of an element of several columns: each after its length."""
    return " || ".join(f"length(cast({p} as varchar)) || ':' || cast({p} as varchar)" for p in parts)


def hashed(x: str, source: str, m: int, by: list[str] = (), seed: int | str = 0, extra: str = "", top: bool = False) -> str:
    """A select of (by..., bucket, y & -y as bit); seed is a number or a column, top takes the cell from the first bits."""
    d = f"md5({f'{seed} || chr(58) || ' if seed else ''}cast({x} as varchar))"
    y = f"(cast('0x' || substr({d}, 18, 15) as bigint) | 1152921504606846976)"
    word = f"cast('0x' || substr({d}, 1, 8) as bigint)"
    cell = f"{word} >> {33 - m.bit_length()}" if top else f"{word} % {m}"
    return f"select {_list(by)}{extra}{cell} as bucket, {y} & -{y} as bit from {source} where {x} is not null"


def cells(x: str, source: str, m: int, by: list[str] = (), seed: int = 0) -> str:
    return f"select {_list(by)}bucket, bit_or(bit) as bitmap from ({hashed(x, source, m, by, seed)}) group by {_list(by)}bucket"


TOP = "case when bitmap = 0 then 0 else length(ltrim(bin(bitmap), '0')) end"
NBR = f"case when bitmap < 2 then 1 else (bitmap >> ({TOP} - 2)) & 1 end"
GAP = "bit_count(bitmap & ~(bitmap + 1))"


def sums(cell_sql: str, m: int, by: list[str] = (), top: str = TOP, nbr: str = NBR, gap: str = GAP) -> str:
    group = f" group by {_list(by)[:-2]}" if by else ""
    return f"""select {_list(by)}count(*) as filled, coalesce(sum(pow(2.0::double, -t)), 0) + {m} - count(*) as s_hll,
      coalesce(sum(pow(2.0::double, -t) * (3 - 2 * n)), 0) + {m} - count(*) as s_nb, coalesce(sum(t::double), 0) as s_top, coalesce(sum(g::double), 0) as s_gap
      from (select {_list(by)}{top} as t, {nbr} as n, {gap} as g from ({cell_sql})){group}"""


def raw(kind: str, m: int) -> str:
    if kind in ("nb", "hll"):
        return f"{lit((gamma(m) if kind == 'nb' else alpha(m)) * m * m)} / s_{kind}"
    scale = LOGLOG * m if kind == "loglog" else m / PHI
    return f"{lit(scale)} * pow(2.0::double, s_{'top' if kind == 'loglog' else 'gap'} / {m})"


def value(kind: str, m: int, small: bool = True, threshold: float = 2.5) -> str:
    r = raw(kind, m)
    linear = f"when {r} < {threshold * m!r} and filled < {m} then {m} * ln({m}::double / ({m} - filled))" if small and kind in ("nb", "hll") else ""
    return f"case when filled = 0 then 0.0 {linear} else {r} end"


def regime(kind: str, m: int, threshold: float = 2.5) -> str:
    return f"case when filled = 0 then 'empty' when {raw(kind, m)} < {threshold * m!r} and filled < {m} then 'linear' else 'raw' end"


def estimate(kind: str, x: str, source: str, m: int, by: list[str] = (), more: str = "", seed: int = 0, threshold: float = 2.5, digits: int = 6, small: bool = True) -> str:
    return f"select {_list(by)}round({value(kind, m, small, threshold)}, {digits}) as estimate{more} from ({sums(cells(x, source, m, by, seed), m, by)})"


def tail_cut(x: str, source: str, order: list[str], m: int, width: int) -> str:
    """(i, t, n): cells of a sequential tail-cut sketch, element by element: a recursion over the ordered stream whose
    state is two lists.  The base is the least register."""
    rows = f"select row_number() over (order by {', '.join(order)}) as seq, bucket + 1 as c, length(ltrim(bin(bit), '0')) as k from ({hashed(x, source, m, extra=', '.join(order) + ', ')})"
    return f"""with recursive rows_ as materialized ({rows}), last_ as (select max(seq) as z from rows_),
    st(seq, ts, ns) as (select 0::bigint, list_transform(range({m}), lambda v: 0), list_transform(range({m}), lambda v: 1) union all
      select r.seq, case when kk > ts[c] then list_transform(ts, lambda v, i: case when i = c then kk else v end) else ts end,
        case when kk > ts[c] then list_transform(ns, lambda v, i: case when i = c then case when kk = 1 or (kk = ts[c] + 1 and ts[c] > 0) then 1 else 0 end else v end)
          when kk = ts[c] - 1 then list_transform(ns, lambda v, i: case when i = c then 1 else v end) else ns end
      from (select r.seq, r.c, least(r.k, list_min(st.ts) + {(1 << width) - 1}) as kk, st.ts, st.ns from st join rows_ r on r.seq = st.seq + 1) r)
    select unnest(range(1, {m + 1})) as i, unnest(ts) as t, unnest(ns) as n from st, last_ where seq = z"""


def changes(kind: str, first: str, order: str, m: int, by: list[str] = ()) -> str:
    """From a select of first arrivals (by..., bucket, bit, order): those that change the state, with q, the chance before."""
    keys, part = _list(by), f"partition by {_list(by)[:-2]}" if by else ""
    if kind == "pcsa":
        changed = f"select *, -0.5::double / bit as delta from ({first})"
    else:
        def term(b: str) -> str:
            t, n = TOP.replace("bitmap", b), NBR.replace("bitmap", b)
            return f"pow(2.0::double, -({t}))" + (f" * (3 - 2 * ({n}))" if kind == "nb" else "")

        prev = f"select *, coalesce(bit_or(bit) over (partition by {keys}bucket order by {order} rows between unbounded preceding and 1 preceding), 0) as prev from ({first})"
        changed = f"select *, {term('(prev | bit)')} - {term('prev')} as delta from ({prev})"
    return f"""select *, ({m} + coalesce(sum(delta) over ({part} order by {order} rows between unbounded preceding and 1 preceding), 0)) / {m} as q
      from ({changed}) where delta <> 0"""


def trace(kind: str, x: str, source: str, order: list[str], m: int, by: list[str] = ()) -> str:
    """The changes of a sequential sketch: (by..., ord, bucket, bit, q)."""
    keys, order_sql = _list(by), ", ".join(order)
    first = f"select {keys}bucket, bit, min(row({order_sql})) as ord from ({hashed(x, source, m, by, extra=order_sql + ', ')}) group by {keys}bucket, bit"
    return changes(kind, first, "ord", m, by)


def martingale(kind: str, x: str, source: str, order: list[str], m: int, by: list[str] = ()) -> str:
    group = f" group by {_list(by)[:-2]}" if by else ""
    return f"select {_list(by)}count(*) as changes, round(sum(1 / q), 6) as est, round(sum((1 - q) / (q * q)), 4) as var from ({trace(kind, x, source, order, m, by)}){group}"


def rse(kind: str, m: int) -> str:
    return lit((variance(kind, m if kind in ("nb", "hll") else None) / m) ** 0.5)


_U = "(8.0::double / m * s / (1 - s))"
F_HLL = "log2((2 + u) / (1 + u))"
F_NB = f"({F_HLL} + log2((4 + 3 * u) / (3 + 3 * u)) - log2((4 + u) / (3 + u)))"


def integrals(source: str) -> str:
    """With i (m, lines, i0, i1, h0, h1), of rows (m, lines): the integrals by the midpoint rule, u = c s / (1 - s)."""
    return f"""with g as (select m, lines, (r.range + 0.5::double) / 40000 as s from {source}, range(40000) r),
w as (select m, lines, {_U} as u, 8.0::double / m / pow(1 - s, 2) / 40000 as w from g),
i as (select m, lines, sum(w * pow({F_NB}, m)) as i0, sum(w * u * pow({F_NB}, m)) as i1, sum(w * pow({F_HLL}, m)) as h0, sum(w * u * pow({F_HLL}, m)) as h1 from w group by m, lines)"""
