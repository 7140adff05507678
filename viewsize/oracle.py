"""The same computations as SQL text for DuckDB, over md5 hashes of 32 or 64 bits, for the registered queries. Nothing of the engine's sketches is used here."""

from __future__ import annotations

import math

from .plans.views import ViewSpec

# Fixed values, written out again: the bias of Probabilistic Counting, the share of empty counters for the linear count, the limit of LogLog's factor.
_PHI, _SWITCH, _ALPHA = 0.77351, 0.051, 0.39701
STAR = """star AS (
  SELECT l.*, o.*, c.*, s.*, p.*, year(l_shipdate) AS sy, month(l_shipdate) AS sm, CAST(l_shipdate AS DATE) AS sd, year(o_orderdate) AS oy, month(o_orderdate) AS om,
         CAST(o_orderdate AS DATE) AS od, nc.n_regionkey AS cr, ns.n_regionkey AS sr
  FROM lineitem l JOIN orders o ON l_orderkey = o_orderkey JOIN customer c ON o_custkey = c_custkey JOIN nation nc ON c_nationkey = nc.n_nationkey
  JOIN supplier s ON l_suppkey = s_suppkey JOIN nation ns ON s_nationkey = ns.n_nationkey JOIN part p ON l_partkey = p_partkey)"""
EVENTS = "ev AS (SELECT *, date_trunc('hour', ts) AS hour, CAST(ts AS DATE) AS day, CAST(floor(value) AS BIGINT) AS v FROM events)"
_TEXT = {"sd": "CAST(sd - DATE '1970-01-01' AS VARCHAR)", "day": "CAST(day - DATE '1970-01-01' AS VARCHAR)", "hour": "CAST(epoch_us(hour) AS VARCHAR)"}


def text(dim: str) -> str:
    return _TEXT.get(dim, f"CAST({dim} AS VARCHAR)")


def _alpha(M: int) -> float:
    return _ALPHA - (2 * math.pi**2 + math.log(2) ** 2) / (48 * M)


def _type(L: int) -> str:
    return "UBIGINT" if L == 64 else "BIGINT"


def hex_of(s: str, L: int = 32) -> str:
    return f"CAST('0x' || substr(md5({s}), 1, {L // 4}) AS {_type(L)})"


def dim_sql(dim: str, seed: str, L: int = 32) -> str:
    return hex_of(f"concat_ws(':', {seed}, '{dim}', 'v', {text(dim)})", L)


def _signed(y: str, L: int) -> str:
    """The hash as the engine prints it: 64 bits are a signed number there."""
    return f"CAST(CAST({y} AS HUGEINT) - CASE WHEN {y} >= 9223372036854775808 THEN 18446744073709551616 ELSE 0 END AS VARCHAR)" if L == 64 else f"CAST({y} AS VARCHAR)"


def tuple_sql(dims: list[str], seed: str, mix: str = "final", L: int = 32) -> str:
    y = dim_sql(dims[0], seed, L)
    for d in dims[1:]:
        y = f"xor({y}, {dim_sql(d, seed, L)})"
    return hex_of(_signed(y, L), L) if mix == "final" else y


def source(view: ViewSpec) -> tuple[str, str]:
    return (EVENTS, "ev") if view.table == "events" else (STAR, "star")


def hashes(view: ViewSpec, seeds: list[int], mix: str = "final", where: str | None = None, L: int = 32) -> str:
    """WITH items ending in t_<view> (distinct tuples) and h_<view> (seed, y)."""
    _, table = source(view)
    dims = ", ".join(view.names)
    cond = f" WHERE {where}" if where else ""
    return (
        f"t_{view.name} AS MATERIALIZED (SELECT DISTINCT {dims} FROM {table}{cond}),\n"
        f"h_{view.name} AS MATERIALIZED (SELECT seed, {tuple_sql(view.names, 'CAST(seed AS VARCHAR)', mix, L)} AS y FROM t_{view.name}, (SELECT unnest({seeds}) AS seed))"
    )


def _zeros(w: str) -> str:
    return f"bit_count(xor({w}, {w} - 1)) - 1"


def _whole(x: str) -> str:
    return f"CAST(round({x}) AS BIGINT)"


def raw_sketch(view: ViewSpec, method: str, M: int, L: int = 32) -> str:
    """SELECT view_id, seed, M, two diagnostics, branch and the estimate as a double, from h_<view>."""
    k, h, name = int(math.log2(M)), f"h_{view.name}", view.name
    head = f"SELECT '{name}' AS view_id, CAST(seed AS INTEGER) AS seed, CAST({M} AS BIGINT) AS M"
    kind = _type(L)
    bucket, rest = f"y & CAST({M - 1} AS {kind})", f"(y >> {k})"
    rank = f"CASE WHEN {rest} = 0 THEN {L - k} ELSE {_zeros(rest)} END"
    if method in ("pc", "pc_guarded"):
        state = f"SELECT seed, {bucket} AS bucket, bit_or(CAST(1 AS {kind}) << ({rank})) AS bits FROM {h} GROUP BY ALL"
        agg = f"SELECT seed, CAST(sum({_zeros('(~bits)')}) AS BIGINT) AS a, {M} - count(*) AS beta FROM ({state}) GROUP BY seed"
        small = f"beta / {M}.0 >= {_SWITCH}" if method == "pc_guarded" else "FALSE"
        return f"{head}, a, beta, CASE WHEN {small} THEN 'linear' ELSE 'counting' END AS branch, CASE WHEN {small} THEN -{M}.0 * ln(beta / {M}.0) ELSE {M / _PHI!r} * pow(2.0, a / {M}.0) END AS est FROM ({agg})"
    if method in ("ll", "ac", "linear"):
        state = f"SELECT seed, {bucket} AS bucket, max({rank}) + 1 AS reg FROM {h} GROUP BY ALL"
        agg = f"SELECT seed, CAST(sum(reg) AS BIGINT) AS a, {M} - count(*) AS beta FROM ({state}) GROUP BY seed"
        linear, loglog = f"CASE WHEN beta > 0 THEN -{M}.0 * ln(greatest(beta, 1) / {M}.0) END", f"{_alpha(M) * M!r} * pow(2.0, a / {M}.0)"
        if method == "ll":
            return f"{head}, a, beta, 'loglog' AS branch, {loglog} AS est FROM ({agg})"
        if method == "linear":
            return f"{head}, a, beta, 'linear' AS branch, {linear} AS est FROM ({agg})"
        small = f"beta / {M}.0 >= {_SWITCH}"
        return f"{head}, a, beta, CASE WHEN {small} THEN 'linear' ELSE 'loglog' END AS branch, CASE WHEN {small} THEN {linear} ELSE {loglog} END AS est FROM ({agg})"
    level = f"CASE WHEN y = 0 THEN {L} ELSE {_zeros('y')} END"
    if method == "maxlevel":
        return f"{head}, a, CAST(0 AS BIGINT) AS beta, 'level' AS branch, pow(2.0, a) AS est FROM (SELECT seed, CAST(max({level}) AS BIGINT) AS a FROM {h} GROUP BY seed)"
    if method.startswith("gc"):
        rows = f"SELECT DISTINCT seed, y FROM {h}" if method == "gc_hashkey" else f"SELECT seed, y FROM {h}"
        cut = f"SELECT seed, y FROM (SELECT seed, y, row_number() OVER (PARTITION BY seed ORDER BY y) AS r FROM ({rows})) WHERE r <= {M}"
        agg = f"SELECT seed, count(*) AS a, max(y) AS beta FROM ({cut}) GROUP BY seed"
        small = "FALSE" if method == "gc_printed" else f"a < {M}"
        return f"{head}, a, beta, CASE WHEN {small} THEN 'exact' ELSE 'ratio' END AS branch, CASE WHEN {small} OR beta = 0 THEN CAST(a AS DOUBLE) ELSE {float(2**L)} * a / beta END AS est FROM ({agg})"
    if method == "lps":
        hist = f"SELECT seed, {level} AS lv, count(*) AS c FROM {h} GROUP BY ALL"
        tail = f"SELECT seed, lv, c, sum(c) OVER (PARTITION BY seed ORDER BY lv DESC) AS tail FROM ({hist})"
        low = f"SELECT *, coalesce(max(CASE WHEN tail > {M} THEN lv END) OVER (PARTITION BY seed) + 1, 0) AS f FROM ({tail})"
        agg = f"SELECT seed, CAST(max(f) AS BIGINT) AS a, CAST(sum(c) AS BIGINT) AS beta FROM ({low}) WHERE lv >= f GROUP BY seed"
        return f"{head}, a, beta, CASE WHEN a = 0 THEN 'exact' ELSE 'scaled' END AS branch, pow(2.0, a) * beta AS est FROM ({agg})"
    raise ValueError(method)


def sketches(views: list[ViewSpec], method: str, ms: list[int], seeds: list[int] = (7,), mix: str = "final", where: str | None = None) -> str:
    """One statement: view_id, seed, M, diagnostics a and b, branch and the rounded estimate."""
    base, _ = source(views[0])
    withs = ",\n".join([base] + [hashes(v, list(seeds), mix, where) for v in views])
    body = "\nUNION ALL\n".join(raw_sketch(v, method, m) for v in views for m in ms)
    return f"WITH {withs}\nSELECT view_id, seed, M, a, beta AS b, branch, {_whole('est')} AS estimate FROM ({body})"


def runs(views: list[ViewSpec], methods: list[str], ms: list[int], n_seeds: int, L: int = 32) -> str:
    """WITH ... runs (view_id, method, M, seed, est, exact)."""
    base, _ = source(views[0])
    withs = ",\n".join([base] + [hashes(v, list(range(n_seeds)), L=L) for v in views])
    body = "\nUNION ALL\n".join(
        f"SELECT view_id, '{m}' AS method, M, seed, est, (SELECT count(*) FROM t_{v.name}) AS exact FROM ({raw_sketch(v, m, M, L)})" for v in views for m in methods for M in ms
    )
    return f"WITH {withs},\nruns AS ({body})"


def exact(view: ViewSpec) -> str:
    base, table = source(view)
    return f"WITH {base} SELECT '{view.name}' AS view_id, count(*) AS exact FROM (SELECT DISTINCT {', '.join(view.names)} FROM {table})"


def _hit(q: str, n: str) -> str:
    """Chance that n draws hit a cell of probability q, without the loss that 1 - (1 - q)^n has for small q."""
    return (
        f"CASE WHEN {q} >= 1 THEN 1.0 WHEN {n} * {q} < 1e-4 THEN {n} * {q} * (1 - ({n} - 1) * {q} / 2 + ({n} - 1) * ({n} - 2) * {q} * {q} / 6) "
        f"ELSE 1 - exp({n} * CASE WHEN {q} < 1e-4 THEN -{q} * (1 + {q} / 2 + {q} * {q} / 3 + {q} * {q} * {q} / 4) ELSE ln(1 - {q}) END) END"
    )


def multifractal(stats: str) -> str:
    """The estimate from SQL for one row (view_id, ratio, seed, n_total, n_sample, f0, m_max): the least number of levels, from log2(f0) to 512, whose
    expected number of hit cells reaches f0, or 512; then the same sum for all facts."""
    cells = "exp(lgamma(k + 1) - lgamma(a + 1) - lgamma(k - a + 1))"
    q = "(pow(p, k - a) * pow(1 - p, a))"
    total = lambda n, rows: f"SELECT k, p, sum({cells} * ({_hit(q, n)})) AS f FROM (SELECT *, unnest(range(k + 1)) AS a FROM ({rows})) GROUP BY k, p"
    levels = "SELECT n_total, n_sample, k, pow(m_max / n_sample, 1.0 / k) AS p FROM (SELECT *, unnest(range(CAST(greatest(1, ceil(log2(f0))) AS BIGINT), 513)) AS k FROM st)"
    return (
        f"WITH st AS (SELECT * FROM ({stats})), fits AS ({total('n_sample', levels)}), best AS (SELECT fits.*, f >= f0 AS reached FROM fits, st ORDER BY f < f0, CASE WHEN f >= f0 THEN k ELSE -k END LIMIT 1), "
        f"last AS ({total('n_total', 'SELECT best.k, best.p, n_total FROM best, st')}) SELECT st.*, CAST(last.k AS INTEGER) AS k, round(last.p, 6) AS bias, reached AS converged, round(last.f, 2) AS estimate FROM st, last, best"
    )
