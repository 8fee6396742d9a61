"""DuckDB SQL that computes the same results by plain means: global sorts, no location of ranks, no driver steps."""

from __future__ import annotations

from privq.functions.domain import Domain
from privq.functions.local import halves
from privq.plans import accountant, counting

KEY = "7"


def uniform(*parts: str | int, key: str = f"'{KEY}'") -> str:
    """SQL of the keyed uniform; a part is a literal number, a quoted string or an SQL expression of whole numbers."""
    text = " || ':' || ".join([key, *[p if str(p).startswith("'") else f"CAST(CAST({p} AS BIGINT) AS VARCHAR)" for p in map(str, parts)]])
    one, two, three, four = (f"CAST(CAST('0x' || substr(sha256({text}), {13 * k + 1}, 13) AS BIGINT) AS DOUBLE)" for k in range(4))
    unit = 2.0**52
    sized = lambda big, small, scale: f"({big} + ({small} + 0.5::DOUBLE) / {unit!r}::DOUBLE) / {scale!r}::DOUBLE"
    return f"least(CASE WHEN {one} > 0 THEN {sized(one, two, unit)} WHEN {two} > 0 THEN {sized(two, three, unit**2)} ELSE {sized(three, four, unit**3)} END, {1 - 2.0**-53!r}::DOUBLE)"


def geometric(scale: float, *parts: str | int, key: str = f"'{KEY}'") -> str:
    one = lambda k: f"CAST(floor(ln({uniform(*parts, k, key=key)}) / {-1.0 / scale!r}) AS BIGINT)"
    return f"({one(0)} - {one(1)})"


def laplace(scale: float, *parts: str | int) -> str:
    return f"(CASE WHEN {uniform(*parts, 1)} < 0.5 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END * {scale!r} * ln({uniform(*parts, 0)}))"


def gumbel(*parts: str | int, key: str = f"'{KEY}'") -> str:
    u = uniform(*parts, key=key)
    return f"(-ln(CASE WHEN {u} < 1e-5 THEN {u} * (1 + {u} * (0.5::DOUBLE + {u} / 3)) ELSE -ln(1 - {u}) END))"


def clamp(x: str, d: Domain) -> str:
    return f"greatest({float(d.lo)!r}, least({float(d.hi)!r}, {x}))"


def quantile_rows(qs: list[float]) -> str:
    return "(VALUES " + ", ".join(f"({i}, CAST({q!r} AS DOUBLE))" for i, q in enumerate(qs, 1)) + ") AS t(i, q)"


def node_rows(m: int, arity: int) -> str:
    """i, sign, l, t of the nodes of every prefix."""
    return "(VALUES " + ", ".join(f"({i}, {s}, {level}, {t})" for i in range(1, m + 1) for s, level, t in counting.nodes(i, m, arity)) + ") AS t(i, s, l, t)"


def prefix_noise(m: int, eps: float, arity: int, key: str = f"'{KEY}'", extra: str = "") -> str:
    """SELECT of i, noise; ``extra`` is a FROM item whose columns the key may use, and ``, g`` of it is kept."""
    z = geometric(counting.node_scale(m, eps, arity), "'cc'", "l", "t", key=key)
    kept = "g, " if extra else ""
    return f"SELECT {kept}i, CAST(sum(s * {z}) AS BIGINT) AS noise FROM {node_rows(m, arity)}{extra} GROUP BY {kept}i"


def select_sql(points: str, eps: float, d: Domain, h: int, target: float | None = None, grid: bool = False, key: str = f"'{KEY}'", keep: str = "i") -> str:
    """CTEs cuts, scored, picked from a relation (i, pos, x)."""
    lo, hi, t = repr(float(d.lo)), repr(float(d.hi)), h + 0.5 if target is None else target
    z = f"lft + len * {uniform(chr(39) + 'pos' + chr(39), 'i', key=key)}"
    return f"""cuts AS (
      SELECT i, pos - 1 AS j, coalesce(lag(cx) OVER (PARTITION BY i ORDER BY pos), {lo}) AS lft, cx AS rgt FROM (SELECT i, pos, {clamp('x', d)} AS cx FROM {points})
      UNION ALL SELECT i, {2 * h + 1}, {clamp('x', d)}, {hi} FROM {points} WHERE pos = {2 * h + 1}),
    scored AS (
      SELECT i, j, lft, rgt - lft AS len, ln(rgt - lft) - {eps / 2!r} * abs(j - {t!r}) AS log_weight, {gumbel("'sel'", 'i', 'j', key=key)} AS g FROM cuts WHERE rgt > lft),
    picked AS (
      SELECT i, {'floor(' + z + ' + 0.5)' if grid else z} AS z FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY log_weight + g DESC, j DESC) AS k FROM scored) WHERE k = 1)"""


def values_cte(relation: str, expr: str, d: Domain) -> str:
    return f"""v AS (SELECT {clamp('x', d)} AS value FROM (SELECT CAST({expr} AS DOUBLE) AS x FROM {relation}) WHERE x IS NOT NULL AND NOT isnan(x)),
    o AS (SELECT value, row_number() OVER (ORDER BY value) AS rn FROM v), n AS (SELECT count(*) AS n FROM v)"""


def noisy_rows(count_eps: float | None) -> str:
    """CTE m over n: the number of rows that ranks are taken of."""
    return "m AS (SELECT n FROM n)" if count_eps is None else f"m AS (SELECT greatest(0, n + {geometric(1 / count_eps, "'n'")}) AS n FROM n)"


def release(relation: str, expr: str, d: Domain, qs: list[float], plan: accountant.Plan, correlated: bool = True, digits: int = 6, count_eps: float | None = None, clip: bool = False) -> str:
    """The release of a column with room; ranks beyond the last row read the upper bound."""
    noise = prefix_noise(plan.m, plan.eps1, plan.arity) if correlated else f"SELECT i, 0 AS noise FROM {quantile_rows(qs)}"
    head = f"""WITH {values_cte(relation, expr, d)}, {noisy_rows(count_eps)},
    r AS (SELECT q.i, q.q, CAST(floor(q.q * m.n + 1e-9) AS BIGINT) + z.noise AS rt FROM (SELECT * FROM {quantile_rows(qs)}) q, m, ({noise}) z WHERE q.i = z.i),
    s AS (SELECT r.i, p.p AS pos, coalesce(o.value, {float(d.hi)!r}) AS x FROM r CROSS JOIN range(1, {2 * plan.h + 2}) AS p(p) LEFT JOIN o ON o.rn = r.rt + p.p - {plan.h + 1})"""
    if clip:
        return f"{head}, {adaptive('s', plan.eps2, d, plan.h, qs)} SELECT CAST(r.i AS INTEGER) AS i, r.q AS q, round(p.z, {digits}) AS z FROM r JOIN estimates p ON r.i = p.i"
    return f"""{head}, {select_sql('s', plan.eps2, d, plan.h, grid=plan.grid)}
    SELECT CAST(r.i AS INTEGER) AS i, r.q AS q, round(p.z, {digits}) AS z FROM r JOIN picked p ON r.i = p.i"""


def adaptive(points: str, eps: float, d: Domain, h: int, qs: list[float]) -> str:
    """CTEs of the levels and estimates (i, z): each slice is cut to the bounds that earlier levels released."""
    parts, known = [], []
    for depth, level in enumerate(halves(len(qs))):
        before = " UNION ALL ".join(known) or "SELECT 0 AS i, 0.0::DOUBLE AS z WHERE false"
        rows = ", ".join(f"({mid + 1}, {a}, {b + 2})" for mid, a, b in level)
        parts.append(f"""b{depth} AS (SELECT e.i, coalesce(p.z, {float(d.lo)!r}) AS lo, coalesce(u.z, {float(d.hi)!r}) AS hi FROM (VALUES {rows}) AS e(i, a, b)
          LEFT JOIN ({before}) p ON p.i = e.a LEFT JOIN ({before}) u ON u.i = e.b),
        x{depth} AS (SELECT t.i, t.pos, greatest(b.lo, least(b.hi, t.x)) AS x, b.lo, b.hi FROM {points} t JOIN b{depth} b ON b.i = t.i),
        c{depth} AS (SELECT i, pos - 1 AS j, coalesce(lag(x) OVER (PARTITION BY i ORDER BY pos), lo) AS lft, x AS rgt FROM x{depth}
          UNION ALL SELECT i, {2 * h + 1}, x, hi FROM x{depth} WHERE pos = {2 * h + 1}),
        l{depth} AS (SELECT b.i, coalesce(k.lft + k.len * {uniform("'pos'", 'b.i')}, b.lo) AS z FROM b{depth} b LEFT JOIN (SELECT i, lft, rgt - lft AS len,
          row_number() OVER (PARTITION BY i ORDER BY ln(rgt - lft) - {eps / 2!r} * abs(j - {h + 0.5!r}) + {gumbel("'sel'", 'i', 'j')} DESC, j DESC) AS k FROM c{depth} WHERE rgt > lft) k ON k.i = b.i AND k.k = 1)""")
        known.append(f"SELECT i, z FROM l{depth}")
    return f"{', '.join(parts)}, estimates AS ({' UNION ALL '.join(known)})"


def grouped(rows: str, groups: list[str], qs: list[float], plan: accountant.Plan, d: Domain, count_eps: float, key: str = KEY) -> str:
    """g, i, q, z of every group; ``rows`` gives (g, value) inside the domain."""
    m, h, margin, own = len(qs), plan.h, plan.margin, f"'{key}/' || g"
    listed = ", ".join(f"({k}, '{g}')" for k, g in enumerate(groups))
    far = 1 << 60
    return f"""WITH v AS ({rows}), h AS (SELECT * FROM (VALUES {listed}) AS t(k, g)),
    o AS (SELECT g, value, row_number() OVER (PARTITION BY g ORDER BY value) AS rn FROM v),
    c AS (SELECT k, g, greatest(0, coalesce(n, 0) + {geometric(1 / count_eps, "'n'", key=own)}) AS n FROM h LEFT JOIN (SELECT g, count(*) AS n FROM v GROUP BY g) USING (g)),
    z AS ({prefix_noise(m, plan.eps1, plan.arity, own, ', h')}),
    t AS (SELECT c.k, c.g, c.n, q.i, q.q, CAST(floor(q.q * c.n + 1e-9) AS BIGINT) AS r, z.noise FROM c, (SELECT * FROM {quantile_rows(qs)}) q, z WHERE z.g = c.g AND z.i = q.i),
    w AS (SELECT *, r + noise AS rt, r - lag(r) OVER (PARTITION BY g ORDER BY i) AS step, r + noise - lag(r + noise) OVER (PARTITION BY g ORDER BY i) AS step2 FROM t),
    ok AS (SELECT g, bool_and(coalesce(step, {far}) > {2 * margin + 1} AND r - {margin} >= 1 AND r <= n - {margin} AND coalesce(step2, {far}) > {2 * h} AND rt - {h} >= 1 AND rt <= n - {h}) AS fits FROM w GROUP BY g),
    r AS (SELECT w.k * {m} + w.i AS k, w.g, w.i, w.q, w.rt FROM w JOIN ok ON ok.g = w.g AND ok.fits),
    s AS (SELECT r.k, r.g, r.i, p.p AS pos, {clamp(f"coalesce(o.value, {float(d.hi)!r})", d)} AS x FROM r CROSS JOIN range(1, {2 * h + 2}) AS p(p) LEFT JOIN o ON o.g = r.g AND o.rn = r.rt + p.p - {h + 1}),
    cuts AS (SELECT k, g, i, pos - 1 AS j, coalesce(lag(x) OVER (PARTITION BY k ORDER BY pos), {float(d.lo)!r}) AS lft, x AS rgt FROM s
      UNION ALL SELECT k, g, i, {2 * h + 1}, x, {float(d.hi)!r} FROM s WHERE pos = {2 * h + 1}),
    best AS (SELECT *, row_number() OVER (PARTITION BY k ORDER BY ln(rgt - lft) - {plan.eps2 / 2!r} * abs(j - {h + 0.5!r}) + {gumbel("'sel'", 'i', 'j', key=own)} DESC, j DESC) AS place FROM cuts WHERE rgt > lft)
    SELECT r.g, r.i, r.q, b.lft + (b.rgt - b.lft) * {uniform("'pos'", 'r.i', key=f"'{key}/' || r.g")} AS z FROM r JOIN best b ON b.k = r.k AND b.place = 1
    UNION ALL SELECT w.g, w.i, w.q, {float(d.lo)!r} + {uniform("'rnd'", 'w.i', key=f"'{key}/' || w.g")} * {float(d.hi - d.lo)!r} FROM w JOIN ok ON ok.g = w.g AND NOT ok.fits"""


def tree_quantiles(relation: str, expr: str, d: Domain, qs: list[float], eps: float, bins: int, arity: int) -> str:
    """Noisy prefix counts made monotone and inverted."""
    width = (d.hi - d.lo) / bins
    return f"""WITH {values_cte(relation, expr, d)}, h AS ({bins_sql(relation, expr, d, bins)}), z AS ({prefix_noise(bins, eps, arity)}),
    c AS (SELECT b + 1 AS b, sum(rows) OVER (ORDER BY b) AS k FROM h),
    u AS (SELECT c.b - 1 AS b, max(greatest(0, c.k + z.noise)) OVER (ORDER BY c.b) AS upto FROM c JOIN z ON z.i = c.b),
    k AS (SELECT b, upto, upto - coalesce(lag(upto) OVER (ORDER BY b), 0) AS k, max(upto) OVER () AS total FROM u),
    f AS (SELECT q.i, q.q, min(k.b) AS b FROM (SELECT * FROM {quantile_rows(qs)}) q JOIN k ON k.upto >= q.q * k.total AND k.k > 0 GROUP BY q.i, q.q)
    SELECT CAST(f.i AS INTEGER) AS i, f.q AS q, round({float(d.lo)!r} + (k.b + (f.q * k.total - (k.upto - k.k)) / k.k) * {width!r}, 6) AS z FROM f JOIN k ON k.b = f.b"""


def index_cte(relation: str, expr: str, d: Domain) -> str:
    """Intervals of the whole column: value, next, upto."""
    return f"""{values_cte(relation, expr, d)},
    c AS (SELECT value, sum(k) AS k FROM (SELECT value, 1 AS k FROM v UNION ALL SELECT {float(d.lo)!r}, 0) GROUP BY value),
    x AS (SELECT value, sum(k) OVER (ORDER BY value) AS upto, coalesce(lead(value) OVER (ORDER BY value), {float(d.hi)!r}) AS nxt FROM c)"""


def _node_pick(name: str, nodes: str, eps: float) -> str:
    """CTE i, z for nodes (i, lo, hi, r) over x."""
    cut = f"SELECT i, r, upto AS j, greatest(value, lo) AS lft, least(nxt, hi) - greatest(value, lo) AS len FROM x JOIN ({nodes}) ON value < hi AND nxt > lo"
    return f"""{name} AS (SELECT i, lft + len * {uniform("'pos'", 'i')} AS z FROM (
      SELECT *, row_number() OVER (PARTITION BY i ORDER BY ln(len) - {eps / 2!r} * abs(j - r) + {gumbel("'bis'", 'i', 'j')} DESC, j DESC) AS k FROM ({cut}) WHERE len > 0) WHERE k = 1)"""


def bisection(relation: str, expr: str, d: Domain, qs: list[float], level_eps: float) -> str:
    """The recursion, one CTE a level; a node's bounds are estimates of earlier levels."""
    m, parts = len(qs), []
    target = f"SELECT i, CAST(floor(q * n + 1e-9) AS BIGINT) AS r FROM {quantile_rows(qs)}, n"
    known: list[str] = []
    for depth, level in enumerate(halves(m)):
        before = " UNION ALL ".join(f"SELECT i, z FROM l{k}" for k in range(depth)) or "SELECT 0 AS i, 0.0 AS z WHERE false"
        rows = ", ".join(f"({mid + 1}, {a}, {b + 2})" for mid, a, b in level)
        nodes = f"""SELECT e.i, t.r, coalesce(p.z, {float(d.lo)!r}) AS lo, coalesce(u.z, {float(d.hi)!r}) AS hi FROM (VALUES {rows}) AS e(i, a, b)
          JOIN ({target}) t ON t.i = e.i LEFT JOIN ({before}) p ON p.i = e.a LEFT JOIN ({before}) u ON u.i = e.b"""
        parts.append(_node_pick(f"l{depth}", nodes, level_eps))
        known.append(f"SELECT i, z FROM l{depth}")
    return f"""WITH {index_cte(relation, expr, d)}, {', '.join(parts)}
    SELECT CAST(q.i AS INTEGER) AS i, q.q AS q, round(p.z, 6) AS z FROM (SELECT * FROM {quantile_rows(qs)}) q JOIN ({' UNION ALL '.join(known)}) p ON p.i = q.i"""


def independent(relation: str, expr: str, d: Domain, qs: list[float], each_eps: float) -> str:
    nodes = f"SELECT i, CAST(floor(q * n + 1e-9) AS BIGINT) AS r, {float(d.lo)!r} AS lo, {float(d.hi)!r} AS hi FROM {quantile_rows(qs)}, n"
    return f"""WITH {index_cte(relation, expr, d)}, {_node_pick('l0', nodes, each_eps)}
    SELECT CAST(q.i AS INTEGER) AS i, q.q AS q, round(p.z, 6) AS z FROM (SELECT * FROM {quantile_rows(qs)}) q JOIN l0 p ON p.i = q.i"""


def bins_sql(relation: str, expr: str, d: Domain, bins: int) -> str:
    """b, rows of all bins."""
    at = f"greatest(0, least({bins - 1}, CAST(floor((value - {float(d.lo)!r}) * {bins / (d.hi - d.lo)!r}) AS BIGINT)))"
    return f"SELECT b.b AS b, coalesce(c.k, 0) AS rows FROM range({bins}) AS b(b) LEFT JOIN (SELECT {at} AS b, count(*) AS k FROM v GROUP BY 1) c ON c.b = b.b"


def histogram(relation: str, expr: str, d: Domain, qs: list[float], eps: float, bins: int) -> str:
    width = (d.hi - d.lo) / bins
    return f"""WITH {values_cte(relation, expr, d)}, h AS ({bins_sql(relation, expr, d, bins)}),
    c AS (SELECT b, greatest(0, rows + {geometric(1 / eps, "'bin'", 'b')}) AS k FROM h),
    u AS (SELECT b, k, sum(k) OVER (ORDER BY b) AS upto, sum(k) OVER () AS total FROM c),
    f AS (SELECT q.i, q.q, min(u.b) AS b FROM (SELECT * FROM {quantile_rows(qs)}) q JOIN u ON u.upto >= q.q * u.total AND u.k > 0 GROUP BY q.i, q.q)
    SELECT CAST(f.i AS INTEGER) AS i, f.q AS q, round({float(d.lo)!r} + (u.b + (f.q * u.total - (u.upto - u.k)) / u.k) * {width!r}, 6) AS z FROM f JOIN u ON u.b = f.b"""
