"""Sampled searches as SQL for DuckDB: the same draws, ranks by a global window, rounds as chained tables.

Intervals are pairs of ranks here, as ranks stand for keys. A search that ends
early has no live interval left, so further rounds change nothing.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

from rangecut.plans import coin

RANGE = coin.RANGE


@dataclass(frozen=True)
class Keyed:
    table: str
    key: str
    order: str
    coin: tuple[str, ...]

    def ranked(self) -> str:
        return f"t AS MATERIALIZED (SELECT *, {self.key} AS k, row_number() OVER (ORDER BY {self.order}) - 1 AS r FROM {self.table}), n AS (SELECT count(*)::BIGINT AS n FROM {self.table})"


LINE_TAG = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_shipdate"
LINE_COIN = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")


def lineitem(key: str = "l_extendedprice") -> Keyed:
    return Keyed("lineitem", key, f"{key} NULLS FIRST, {LINE_TAG}", LINE_COIN)


def orders(key: str = "o_totalprice") -> Keyed:
    return Keyed("orders", key, f"{key} NULLS FIRST, o_orderkey", ("o_orderkey",))


def customers() -> Keyed:
    return Keyed("customer", "c_acctbal", "c_acctbal NULLS FIRST, c_custkey", ("c_custkey",))


def chance(numerator: str, denominator: str) -> str:
    return f"CASE WHEN {numerator} >= {denominator} THEN {RANGE} ELSE ({numerator}) * {RANGE} // ({denominator}) END"


def rounds(keyed: Keyed, parts: int, eps: float, seed: int, limits: list[str], *, stream: str | None = None, kind: str = "bernoulli", beta: int = 0, per_proc: int = 0, proc: str = "", stop: bool = True) -> str:
    """CTEs s0..sK (i, ideal, lo, hi) and tr1..trK (one row each) for the thresholds ``limits``, expressions over n and live."""
    e = Fraction(str(eps))
    error = lambda s: f"least(CASE WHEN {s}lo >= 0 THEN abs({s}lo * {parts} - {s}ideal) ELSE 1000000000000000000 END, CASE WHEN {s}hi < n.n THEN abs({s}hi * {parts} - {s}ideal) ELSE 1000000000000000000 END)"
    settled = lambda s: f"(2 * {e.denominator} * {error(s)} <= {e.numerator} * n.n)"
    out = [keyed.ranked(), f"s0 AS (SELECT i, n.n * i AS ideal, -1::BIGINT AS lo, n.n AS hi FROM range(1, {parts}) x(i), n)"]
    for j, limit in enumerate(limits, 1):
        open_ = f"NOT {settled('s.')}".replace("1000000000000000000", "100000000000000")
        out.append(f"g{j} AS MATERIALIZED (SELECT lo, hi, count(*)::BIGINT AS sharing FROM s{j - 1} s, n WHERE hi - lo > 1 AND {open_} GROUP BY lo, hi)")
        out.append(f"z{j} AS (SELECT coalesce(sum(hi - lo - 1), 0)::BIGINT AS live FROM g{j})")
        draw = coin.draw_sql(keyed.coin, seed, stream or j)
        if kind == "per_interval":
            picked = f"SELECT r, g.lo FROM t, g{j} g WHERE r > g.lo AND r < g.hi AND {draw} < {chance(f'{beta} * g.sharing', '(g.hi - g.lo - 1)')}"
            shown = f"(SELECT max({chance(f'{beta} * sharing', '(hi - lo - 1)')}) FROM g{j})"
        elif kind == "draw_discard":
            shown = f"(SELECT ({per_proc} * n.n + live - 1) // greatest(live, 1) FROM n, z{j})"
            picked = f"SELECT r, g.lo FROM (SELECT *, row_number() OVER (PARTITION BY {proc} ORDER BY {draw}, r) AS nth FROM t) t, g{j} g WHERE r > g.lo AND r < g.hi AND nth <= {shown}"
        else:
            shown = f"(SELECT {limit} FROM n, z{j})"
            picked = f"SELECT r, g.lo FROM t, g{j} g WHERE r > g.lo AND r < g.hi AND {draw} < {shown}"
        out.append(f"p{j} AS MATERIALIZED ({picked})")
        out.append(
            f"s{j} AS MATERIALIZED (SELECT i, ideal, greatest(s.lo, coalesce((SELECT max(r) FROM p{j} WHERE r * {parts} <= s.ideal), -1)) AS lo, "
            f"least(s.hi, coalesce((SELECT min(r) FROM p{j} WHERE r * {parts} >= s.ideal), n.n)) AS hi FROM s{j - 1} s, n)"
        )
        left = f"(SELECT coalesce(sum(hi - lo - 1), 0)::BIGINT FROM (SELECT DISTINCT lo, hi FROM s{j} s, n WHERE hi - lo > 1 AND {open_}))"
        out.append(
            f"tr{j} AS (SELECT {j} AS round, {shown}::BIGINT AS threshold, (SELECT count(*) FROM p{j})::BIGINT AS sample_size, (SELECT live FROM z{j}) AS live_before, "
            f"{left} AS live_after, (SELECT count(*) FROM s{j} s, n WHERE {open_})::BIGINT AS unsettled)"
        )
    last = len(limits)
    out.append(
        f"chosen AS (SELECT i, ideal, n.n AS n, CASE WHEN lo < 0 AND hi >= n.n THEN NULL WHEN lo < 0 THEN hi WHEN hi >= n.n THEN lo "
        f"WHEN abs(lo * {parts} - ideal) <= abs(hi * {parts} - ideal) THEN lo ELSE hi END AS r, {settled('s.').replace('1000000000000000000', '100000000000000')} AS settled FROM s{last} s, n)"
    )
    return "WITH " + ",\n".join(out) + "\n"


def splitters(*args, **options) -> str:
    return rounds(*args, **options) + "SELECT i::INTEGER AS i, chosen.r AS split_rank, t.k AS split_key, settled FROM chosen LEFT JOIN t USING (r)"


def trace(*args, **options) -> str:
    limits = args[4]
    union = " UNION ALL ".join(f"SELECT * FROM tr{j}" for j in range(1, len(limits) + 1))
    return rounds(*args, **options) + f"SELECT round::INTEGER AS round, threshold, sample_size, live_before, live_after, unsettled FROM ({union}) WHERE live_before > 0"


def totals(*args, **options) -> str:
    """One row: how many rounds there were, and how many keys they sampled."""
    return f"SELECT count(*)::BIGINT AS rounds, coalesce(sum(sample_size), 0)::BIGINT AS probes FROM ({trace(*args, **options)})"


def loads(*args, **options) -> str:
    """Rows between the cuts that the search chose; empty ranges are left out, the others numbered from 1."""
    return rounds(*args, **options) + (
        "SELECT row_number() OVER (ORDER BY r)::INTEGER AS nth, rows FROM (SELECT r, lead(r, 1, any_value(n.n)) OVER (ORDER BY r) - r AS rows FROM "
        "(SELECT 0::BIGINT AS r UNION SELECT r FROM chosen WHERE r IS NOT NULL) c, n GROUP BY r) WHERE rows > 0"
    )


def summary(*args, **options) -> str:
    """One row: rounds, keys sampled, and the rows of the largest range."""
    union = " UNION ALL ".join(f"SELECT sample_size, live_before FROM tr{j}" for j in range(1, len(args[4]) + 1))
    return rounds(*args, **options) + (
        f"SELECT count(*)::BIGINT AS rounds, sum(sample_size)::BIGINT AS probes, (SELECT max(rows) FROM (SELECT lead(r, 1, n.n) OVER (ORDER BY r) - r AS rows FROM "
        f"(SELECT 0::BIGINT AS r UNION SELECT r FROM chosen WHERE r IS NOT NULL) c, n))::BIGINT AS peak FROM ({union}) WHERE live_before > 0"
    )


def rounds_over_seeds(keyed: Keyed, parts_list: tuple[int, ...], eps: float, seeds: int, beta: int = 1) -> str:
    """Rounds of all seeds together for each method and number of parts, until nothing is live: a recursion with as many steps as that takes."""
    e = Fraction(str(eps))
    far = "100000000000000"
    error = f"least(CASE WHEN lo >= 0 THEN abs(lo * p - n * i) ELSE {far} END, CASE WHEN hi < n THEN abs(hi * p - n * i) ELSE {far} END)"
    live = f"(hi - lo > 1 AND 2 * {e.denominator} * {error} > {e.numerator} * n)"
    draw = "('0x' || substr(md5(" + " || '|' || ".join(["seed", "(j + 1)", *keyed.coin]) + "), 1, 8))::BIGINT"
    limit = f"CASE WHEN method = 'narrowing' THEN {chance(f'{beta} * p', 'size')} ELSE {chance(f'{beta} * sharing', '(hi - lo - 1)')} END"
    return (
        f"WITH RECURSIVE {keyed.ranked()}, s(j, method, p, seed, i, n, lo, hi) AS ("
        f"SELECT 0::BIGINT, method, p::BIGINT, seed, i, n.n, -1::BIGINT, n.n FROM (VALUES ('narrowing'), ('per interval')) m(method), (SELECT unnest({list(parts_list)}) AS p) q, range(1, {seeds + 1}) x(seed), range(1, {max(parts_list)}) y(i), n WHERE i < p "
        f"UNION ALL (WITH g AS MATERIALIZED (SELECT *, sum(hi - lo - 1) OVER (PARTITION BY method, p, seed)::BIGINT AS size FROM (SELECT j, method, p, seed, lo, hi, count(*)::BIGINT AS sharing FROM s WHERE {live} GROUP BY ALL)), "
        f"k AS MATERIALIZED (SELECT g.method, g.p, g.seed, g.lo, g.hi, t.r FROM g JOIN t ON t.r > g.lo AND t.r < g.hi WHERE {draw} < {limit}) "
        "SELECT j + 1, s.method, s.p, s.seed, i, n, greatest(s.lo, coalesce(max(r) FILTER (WHERE r * s.p <= n * i), -1)), least(s.hi, coalesce(min(r) FILTER (WHERE r * s.p >= n * i), n)) "
        "FROM (SELECT * FROM s SEMI JOIN g USING (method, p, seed)) s LEFT JOIN k ON k.method = s.method AND k.p = s.p AND k.seed = s.seed AND k.lo = s.lo AND k.hi = s.hi GROUP BY s.j, s.method, s.p, s.seed, i, n, s.lo, s.hi)) "
        f"SELECT method, p::INTEGER AS parts, (count(DISTINCT (j, seed)) FILTER (WHERE {live}))::BIGINT AS rounds FROM s GROUP BY method, p"
    )


def bisection(source: str, parts: int, eps: float, low: int, high: int, most: int) -> str:
    """One row: rounds and probes of halving the values of ``code`` in ``source``, and how many splitters stay open."""
    e = Fraction(str(eps))
    out = [
        f"v AS MATERIALIZED (SELECT code FROM {source})",
        "n AS (SELECT count(*)::BIGINT AS n FROM v)",
        "upto AS MATERIALIZED (SELECT code, sum(count(*)) OVER (ORDER BY code)::BIGINT AS rows FROM v GROUP BY code)",
        f"b0 AS (SELECT i, {low}::BIGINT AS a, {high + 1}::BIGINT AS b, NULL::BIGINT AS err FROM range(1, {parts}) x(i))",
    ]
    is_open = f"(err IS NULL OR 2 * {e.denominator} * err > {e.numerator} * n.n)"
    for j in range(1, most + 1):
        out.append(f"h{j} AS MATERIALIZED (SELECT DISTINCT a + (b - a) // 2 AS p FROM b{j - 1}, n WHERE {is_open} AND b - a > 1)")
        out.append(f"k{j} AS MATERIALIZED (SELECT p, coalesce(rows, 0) AS rk FROM h{j} ASOF LEFT JOIN upto ON h{j}.p > upto.code)")
        out.append(
            f"b{j} AS MATERIALIZED (SELECT i, CASE WHEN rk * {parts} < n.n * i THEN p ELSE a END AS a, CASE WHEN rk * {parts} >= n.n * i THEN p ELSE b END AS b, "
            f"CASE WHEN rk IS NULL THEN err ELSE least(err, abs(rk * {parts} - n.n * i)) END AS err "
            f"FROM (SELECT s.*, k.p, k.rk FROM b{j - 1} s CROSS JOIN n LEFT JOIN k{j} k ON k.p = s.a + (s.b - s.a) // 2 AND {is_open} AND s.b - s.a > 1), n)"
        )
    probes = " UNION ALL ".join(f"SELECT {j} AS j, count(*) AS m FROM h{j}" for j in range(1, most + 1))
    return f"WITH {', '.join(out)} SELECT count(*)::BIGINT AS rounds, sum(m)::BIGINT AS probes, (SELECT count(*) FROM b{most}, n WHERE {is_open})::BIGINT AS left_open FROM ({probes}) WHERE m > 0"


def geometric_limits(parts: int, ratios: list[float]) -> list[str]:
    return [chance(str(max(1, int(parts * s + 0.5))), "n.n") for s in ratios]


def budget_limits(parts: int, budget: int, count: int) -> list[str]:
    return [chance(str(budget * parts), "greatest(live, 1)")] * count
