"""Pieces of SQL that say what the queries should return, for an engine without this package."""

from __future__ import annotations

from distinct_bounds.functions.special import EULER, LN2

SLOTS, STEPS, P = 64, 256, 1 / 16


def words(source: str, key: str, by: str = "", lanes: int = 4, distinct: bool = True) -> str:
    """CTEs o and f: hash fields of each key of a source in each lane, cut at hex digits."""
    names = f"{by}, " if by else ""
    return f"""
o AS (SELECT {'DISTINCT ' if distinct else ''}{names}CAST({key} AS VARCHAR) AS k FROM {source} WHERE {key} IS NOT NULL),
g AS (SELECT {names}k, lane, substr(sha256(k), CAST(16 * lane + 1 AS BIGINT), 16) AS w FROM o, (SELECT CAST(unnest(range({lanes})) AS INTEGER) AS lane) t),
h AS (SELECT {names}k, lane, CAST(CAST('0x' || substr(w, 1, 1) AS UBIGINT) AS INTEGER) AS "row", CAST(CAST('0x' || substr(w, 15, 2) AS UBIGINT) AS INTEGER) AS z, CAST(CAST('0x' || substr(w, 2, 13) AS UBIGINT) AS BIGINT) AS v FROM g),
f AS (SELECT {names}k, lane, "row", z, v, CAST(CASE WHEN v = 0 THEN 53 ELSE 53 - length(bin(v)) END AS INTEGER) AS x FROM h)"""


def slots(source: str, key: str, by: str = "") -> str:
    """words() and CTE s: the slots."""
    names = f"{by}, " if by else ""
    return words(source, key, by) + f""",
s AS (SELECT {names}lane, "row", max(CAST(x AS BIGINT) * 256 + 255 - z) AS key FROM f GROUP BY {names}lane, "row")"""


def means(by: str = "", empty: float = 0.0, source: str = "s") -> str:
    """CTE m: the mean of the slots' values, empty ones at a given value."""
    names, group = (f"{by}, ", f" GROUP BY {by}") if by else ("", "")
    return f"""
m AS (SELECT {names}(coalesce(sum(key // 256 - log2(1 + (255 - key % 256) / 256.0)), 0) + (64 - count(key)) * {empty!r}) / 64 AS mean_y, count(key) AS filled FROM {source}{group})"""


def levels(n: int, p: float = P, over: str | None = "m") -> str:
    """CTE t: the level of each whole number of objects up to n, and to e times the largest estimate of CTE `over`; 0 has level 0."""
    end = f"{n + 1}" if over is None else f"(SELECT CAST(greatest({n}, ceil(exp(max(mean_y) * {LN2!r} + {1 - EULER!r}) / {p!r})) AS BIGINT) + 1 FROM {over})"
    return f"""
t AS (SELECT 0 AS n, 0.0::DOUBLE AS hp UNION ALL SELECT n, sum((1 - pow({1 - p!r}, n)) / n) OVER (ORDER BY n) AS hp FROM (SELECT unnest(range(1, {end})) AS n))"""


def half(side: str, tail: float, slots: int = SLOTS) -> str:
    """Half-width of a side as a subquery: the least of the dual form over a fine grid of tilts, from lgamma alone."""
    y = f"(-ln({tail!r}) / {slots})"
    if side == "lower":  # 1 - t is made apart, as it is what matters near 1
        return f"(SELECT min(({y} + lgamma(rest)) / t) - {EULER!r} FROM (SELECT 1 / (1 + exp(9 - i * 2.2e-4)) AS t, 1 / (1 + exp(i * 2.2e-4 - 9)) AS rest FROM (SELECT unnest(range(100000)) AS i)))"
    return f"(SELECT min(({y} + lgamma(1 + t)) / t) + {EULER!r} FROM (SELECT exp(-9 + i * 1.2e-4) AS t FROM (SELECT unnest(range(100000)) AS i)))"


def digamma(x: str, order: int = 0) -> str:
    """Digamma of a positive expression: ten steps of the recurrence and the asymptotic series."""
    z = f"({x} + 10)"
    steps = " + ".join(f"1 / ({x} + {k})" for k in range(10))
    return f"(ln{z} - 1 / (2 * {z}) - 1 / (12 * {z} * {z}) + 1 / (120 * pow({z}, 4)) - 1 / (252 * pow({z}, 6)) + 1 / (240 * pow({z}, 8)) - ({steps}))"


def shortest(cases: str) -> str:
    """CTE x: (alpha, a0, down, up, lower_tail) of the shortest interval of each (alpha, a0) of a query.

    The lower bound's tilt is bisected. It fixes that side's half-width and tail; the other
    side has what is left of the tail, and its tilt is the ratio by which the width stands still.
    """
    t1, t2 = "t", "u"
    return f"""
x AS (WITH RECURSIVE c AS ({cases}), b AS (
  SELECT 0 AS i, CAST(alpha AS DOUBLE) AS alpha, a0, 1e-9 AS lo, 1 - 1e-9 AS hi FROM c
  UNION ALL
  SELECT i + 1, alpha, a0, CASE WHEN rest <= 0 OR u > 1e6 OR u * {digamma('(1 + u)')} - lgamma(1 + u) > -ln(rest) / a0 THEN t ELSE lo END, CASE WHEN rest <= 0 OR u > 1e6 OR u * {digamma('(1 + u)')} - lgamma(1 + u) > -ln(rest) / a0 THEN hi ELSE t END
  FROM (SELECT *, CASE WHEN rest > 0 THEN tail * t / rest ELSE 1e9 END AS u FROM (SELECT *, 1 - alpha - tail AS rest FROM (SELECT *, exp(-a0 * (-t * {digamma('(1 - t)')} - lgamma(1 - t))) AS tail FROM (SELECT *, (lo + hi) / 2 AS t FROM b WHERE i < 60))))
), e AS (SELECT alpha, a0, (lo + hi) / 2 AS t FROM b WHERE i = 60),
f AS (SELECT alpha, a0, t, exp(-a0 * (-t * {digamma('(1 - t)')} - lgamma(1 - t))) AS lower_tail FROM e),
g AS (SELECT *, lower_tail * t / (1 - alpha - lower_tail) AS u FROM f)
SELECT alpha, a0, -{digamma('(1 - t)')} - {EULER!r} AS down, {digamma('(1 + u)')} + {EULER!r} AS up, lower_tail FROM g)"""


def _xx_round(x: str, r: int) -> str:
    return f"((({x}) * {1 << r}::UHUGEINT) % {1 << 64}::UHUGEINT + ({x}) // {1 << (64 - r)}::UHUGEINT)"


# The primes of the hash.
XX = (11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261)


def xx_slots(source: str, key: str, lanes: int = 4) -> str:
    """CTE s: the slots by seeded 64-bit words of a hash that the other engine lacks, for keys of at most 31 ASCII characters."""
    m = f"{1 << 64}::UHUGEINT"
    p1, p2, p3, p4, p5 = (f"{x}::UHUGEINT" for x in XX)
    v, kind = f"(e % {m})", f"(e // {m})"
    eight = _xx_round(f"xor(h, {_xx_round(f'({v} * {p2}) % {m}', 31)} * {p1} % {m})", 27)
    four = _xx_round(f"xor(h, ({v} * {p1}) % {m})", 23)
    one = _xx_round(f"xor(h, ({v} * {p5}) % {m})", 11)
    step = f"lambda h, e: CASE {kind} WHEN 1 THEN ({eight} * {p1} % {m} + {p4}) % {m} WHEN 2 THEN ({four} * {p2} % {m} + {p3}) % {m} ELSE {one} * {p1} % {m} END"

    def end(x: str, shift: int, prime: str | None) -> str:
        mixed = f"xor({x}, {x} // {1 << shift}::UHUGEINT)"
        return f"{mixed} * {prime} % {m}" if prime else mixed

    def little(at: str, n: int) -> str:
        return "CAST('0x' || " + " || ".join(f"substr(hx, {at} + {2 * i + 1}, 2)" for i in reversed(range(n))) + " AS UBIGINT)::UHUGEINT"

    def parts(n: int, count: str, start: str, kind: int) -> str:
        return f"list_transform(range({count}), lambda i: {kind}::UHUGEINT * {m} + {little(f'{start} + {2 * n} * i', n)})"

    body = f"list_concat(list_concat({parts(8, 'n // 8', '0', 1)}, {parts(4, '(n % 8) // 4', '16 * (n // 8)', 2)}), {parts(1, 'n % 4', '8 * (n // 4)', 3)})"
    return f"""
o AS (SELECT DISTINCT CAST({key} AS VARCHAR) AS k FROM {source} WHERE {key} IS NOT NULL),
l0 AS (SELECT lane, list_reduce([(42::UHUGEINT + {p5} + 4) % {m}, 2::UHUGEINT * {m} + lane::UHUGEINT], {step}) AS a FROM (SELECT CAST(unnest(range({lanes})) AS INTEGER) AS lane)),
l1 AS (SELECT lane, {end('a', 33, p2)} AS a FROM l0), l2 AS (SELECT lane, {end('a', 29, p3)} AS a FROM l1), l3 AS (SELECT lane, {end('a', 32, None)} AS seed FROM l2),
k0 AS (SELECT k, hex(k) AS hx, CAST(strlen(k) AS BIGINT) AS n FROM o),
k1 AS (SELECT k, n, {body} AS body FROM k0),
w0 AS (SELECT lane, list_reduce(list_concat([(seed + {p5} + n::UHUGEINT) % {m}], body), {step}) AS a FROM k1, l3),
w1 AS (SELECT lane, {end('a', 33, p2)} AS a FROM w0), w2 AS (SELECT lane, {end('a', 29, p3)} AS a FROM w1), w3 AS (SELECT lane, CAST({end('a', 32, None)} AS UBIGINT) AS w FROM w2),
h AS (SELECT lane, CAST(w >> 60 AS INTEGER) AS "row", CAST(w & 255 AS BIGINT) AS z, CAST((w >> 8) & {(1 << 52) - 1} AS BIGINT) AS v FROM w3),
s AS (SELECT lane, "row", max((53 - CASE WHEN v = 0 THEN 0 ELSE length(bin(v)) END) * 256 + 255 - z) AS key FROM h GROUP BY lane, "row")"""


def floors(by: str, down: float | str | None, up: float | str | None, below: float = 1 / 256, above: float = 0.0, extra: str = "", source: str = "m") -> str:
    """SELECT of the floors of estimate, lower and upper bound for each row of m, by as-of joins with t."""
    names = f"{by}, " if by else ""
    cols, sides, joins = [f"{names}e.n AS estimate_int"], [f"mean_y * {LN2!r} AS _middle"], ["ASOF JOIN t e ON _middle >= e.hp"]
    if down is not None:
        cols.append("l.n AS lower_floor")
        sides.append(f"greatest(0.0, mean_y * {LN2!r} - ({down} + {below!r})) AS _low")
        joins.append("ASOF JOIN t l ON _low >= l.hp")
    if up is not None:
        cols.append("u.n AS upper_floor")
        sides.append(f"mean_y * {LN2!r} + ({up} + {above!r}) AS _high")
        joins.append("ASOF JOIN t u ON _high >= u.hp")
    return f"SELECT {', '.join(cols)}{extra} FROM (SELECT {source}.*, {', '.join(sides)} FROM {source}) {source} {' '.join(joins)}"


def reals(columns: dict[str, str], source: str, keep: str = "") -> str:
    """CTE v: keep and, for each name, the real number whose level an expression over the source is.

    The exponential of the level is all but a straight line, so a number is read off a
    polynomial in it through four whole numbers.
    """
    sides = ", ".join(f"exp({level}) AS _{n}" for n, level in columns.items())
    joins = " ".join(f"ASOF JOIN t2 {n}_ ON _{n} >= {n}_.g0" for n in columns)

    def read(n: str) -> str:
        terms = []
        for i in range(1, 4):
            others = [j for j in range(4) if j != i]
            above = " * ".join(f"(_{n} - {n}_.g{j})" for j in others)
            below = " * ".join(f"({n}_.g{i} - {n}_.g{j})" for j in others)
            terms.append(f"{i} * {above} / ({below})")
        return f"{n}_.n + {' + '.join(terms)} AS {n}"

    leads = ", ".join(f"lead(exp(hp), {i}) OVER (ORDER BY n) AS g{i}" for i in range(1, 4))
    return f"""
t2 AS (SELECT n, exp(hp) AS g0, {leads} FROM t),
v AS (SELECT {keep}{', ' if keep else ''}{', '.join(read(n) for n in columns)} FROM (SELECT *, {sides} FROM {source}) {joins})"""


def chi_square_tail(x: str, df: str) -> str:
    """Upper tail by summing the density over a fine grid from x on."""
    return f"(SELECT sum(exp((({df}) / 2.0 - 1) * ln(s) - s / 2 - lgamma(({df}) / 2.0) - ({df}) / 2.0 * ln(2.0))) * w FROM (SELECT ({x}) + (i + 0.5) * (({x}) + 40 * ({df}) + 200) / 50000 AS s, (({x}) + 40 * ({df}) + 200) / 50000 AS w FROM (SELECT unnest(range(50000)) AS i)) GROUP BY w)"


def f_tail(f: str, df1: str, df2: str) -> str:
    """Upper tail of F by the beta integral, with the root of 1 - b as variable, so that one numerator degree is smooth too."""
    b = f"(({df2}) / (({df2}) + ({df1}) * ({f})))"
    front = f"exp(lgamma((({df1}) + ({df2})) / 2.0) - lgamma(({df1}) / 2.0) - lgamma(({df2}) / 2.0))"
    return f"(SELECT 2 * {front} * sum(pow(s, ({df1}) - 1) * pow(1 - s * s, ({df2}) / 2.0 - 1)) * w FROM (SELECT r + (i + 0.5) * (1 - r) / 100000 AS s, (1 - r) / 100000 AS w FROM (SELECT sqrt(1 - {b}) AS r), (SELECT unnest(range(100000)) AS i)) GROUP BY w)"


def with_(*parts: str) -> str:
    return "WITH " + ",".join(parts)
