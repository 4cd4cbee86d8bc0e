"""Pieces of DuckDB SQL that the oracles are put together from. Vectors are rows (item_id, n, p)."""

from __future__ import annotations

from prefbook.operators.simplex import BOOK_SEED
from prefbook.sources.tables import FIXTURES

_SOURCE = {
    "events": "SELECT json_extract_string(props, '$.k')::BIGINT AS item_id, event_type AS symbol, 1.0::DOUBLE AS weight FROM events",
    "parts": "SELECT l_partkey AS item_id, l_returnflag AS symbol, l_quantity::DOUBLE AS weight FROM lineitem",
    "suppliers": "SELECT l_suppkey AS item_id, l_returnflag || l_linestatus AS symbol, l_quantity::DOUBLE AS weight FROM lineitem",
    "customers": "SELECT o_custkey AS item_id, o_orderpriority AS symbol, o_totalprice::DOUBLE AS weight FROM orders",
    "quarters": "SELECT o_custkey AS item_id, quarter(o_orderdate)::VARCHAR AS symbol, o_totalprice::DOUBLE AS weight FROM orders",
}
PLOGP = "CASE WHEN p > 0 THEN -p * log2(p) ELSE 0 END"
PLOGQ = "CASE WHEN p <= 0 THEN 0 WHEN q <= 0 THEN 'Infinity'::DOUBLE ELSE -p * log2(q) END"


def uniform(seed: str, key: str, draw: str) -> str:
    return f"((('0x' || substr(md5({seed} || '|' || {key} || '|' || {draw}), 1, 8))::BIGINT + 0.5) / 4294967296.0)"


def source(name: str) -> str:
    """Rows (item_id, symbol, weight) of a fixture."""
    return _SOURCE[name]


def requests() -> str:
    return "req AS (SELECT event_id, user_id, json_extract_string(props, '$.k')::BIGINT AS item_id, event_type AS symbol, ts FROM events)"


def spv(name: str) -> str:
    """src, alpha, spv(item_id, n, p), tot(item_id, t), dem(item_id, f)."""
    alpha = ", ".join(f"('{a}', {i})" for i, a in enumerate(FIXTURES[name].alphabet))
    return f"""src AS ({_SOURCE[name]}),
alpha(symbol, n) AS (VALUES {alpha}),
cnt AS (SELECT item_id, n, count(*) AS c FROM src JOIN alpha USING (symbol) GROUP BY 1, 2),
tot AS (SELECT item_id, sum(c) AS t FROM cnt GROUP BY 1),
spv AS (SELECT t.item_id, a.n, coalesce(c.c, 0)::DOUBLE / t.t::DOUBLE AS p FROM tot t CROSS JOIN alpha a LEFT JOIN cnt c ON c.item_id = t.item_id AND c.n = a.n),
dem AS (SELECT item_id, sum(weight) / sum(sum(weight)) OVER () AS f FROM src GROUP BY 1)"""


def simplex(n: int, seed: int, ids: str) -> str:
    """spv of hashed uniform points for the ids of a subquery, and equal demand."""
    return f"""ids AS ({ids}),
raw AS (SELECT item_id, n, -ln({uniform(f"'{seed}'", "item_id", "n")}) AS e FROM ids, range({n}) r(n)),
spv AS (SELECT item_id, n, e / sum(e) OVER (PARTITION BY item_id) AS p FROM raw),
dem AS (SELECT item_id, 1.0 / count(*) OVER () AS f FROM ids)"""


def lattice(grid: int, name: str = "spv") -> str:
    return f"""{name}_cells AS (
    SELECT ((d * {grid} + a) * {grid} + b)::BIGINT AS item_id, (a + (d + 1) / 3.0) / {grid} AS x, (b + (d + 1) / 3.0) / {grid} AS y
    FROM range({grid}) r(a), range({grid}) s(b), range(2) t(d) WHERE a + b < {grid} AND (d = 0 OR a + b < {grid} - 1)),
{name} AS (SELECT item_id, 0 AS n, x AS p FROM {name}_cells UNION ALL SELECT item_id, 1, y FROM {name}_cells UNION ALL SELECT item_id, 2, 1.0 - x - y FROM {name}_cells)"""


def density(kind: str, n: int) -> str:
    """dem(item_id, f) of the points in spv."""
    g = "1.0" if kind == "uniform" else f"sqrt(sum(pow(p - 1.0 / {n}, 2)))"
    return f"dens AS (SELECT item_id, {g} AS g FROM spv GROUP BY item_id), dem AS (SELECT item_id, g / sum(g) OVER () AS f FROM dens)"


def books(n: int, k: int, seed: int = BOOK_SEED, name: str = "books") -> str:
    """Portable books (k, n, q)."""
    return f"{name} AS (SELECT k, n, e / sum(e) OVER (PARTITION BY k) AS q FROM (SELECT k, n, -ln({uniform(f"'{seed}'", 'k', 'n')}) AS e FROM range({k}) a(k), range({n}) b(n)))"


def entropy() -> str:
    return f"ent AS (SELECT item_id, sum({PLOGP}) AS h FROM spv GROUP BY item_id)"


def costs(of: str = "books", into: str = "cost") -> str:
    return f"{into} AS (SELECT item_id, k, sum({PLOGQ}) AS c FROM spv JOIN {of} USING (n) GROUP BY item_id, k)"


def best(of: str = "cost", into: str = "best") -> str:
    return f"{into} AS (SELECT item_id, k, c FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY c, k) AS rn FROM {of}) WHERE rn = 1)"


def priced(n: int, k: int) -> str:
    """books, ent, cost and best."""
    return ", ".join([books(n, k), entropy(), costs(), best()])


def collapsed() -> str:
    """types: vectors of merged items replace spv and dem; the least id stands for a type."""
    return """vec AS (SELECT item_id, list(p ORDER BY n) AS v FROM spv GROUP BY item_id),
types AS (SELECT min(item_id) AS item_id, v, sum(f) AS f FROM vec JOIN dem USING (item_id) GROUP BY v),
tspv AS (SELECT item_id, unnest(range(len(v))) AS n, unnest(v) AS p, f FROM types),
tent AS (SELECT item_id, any_value(f) AS f, sum(CASE WHEN p > 0 THEN -p * log2(p) ELSE 0 END) AS h FROM tspv GROUP BY item_id)"""


def seeded(k: int, seed: int, power: float) -> list[str]:
    """s0, s1, ...: the seeds of a run over types, each (k, n, q), all seeds so far."""
    out = []
    for d in range(k):
        u = uniform(f"'{seed}'", "item_id", f"{d + 1}")
        if d:
            out.append(f"g{d} AS (SELECT item_id, min(c) AS c FROM (SELECT item_id, k, sum({PLOGQ}) AS c FROM tspv JOIN s{d - 1} USING (n) GROUP BY item_id, k) GROUP BY item_id)")
            weight, source = f"f * pow(greatest(0.0, c - h), {power})", f"tent JOIN g{d} USING (item_id)"
        else:
            weight, source = "f", "tent"
        out.append(f"w{d} AS (SELECT arg_min(item_id, [-ln({u}) / weight, item_id::DOUBLE]) AS item_id FROM (SELECT item_id, {weight} AS weight FROM {source}) WHERE weight > 0)")
        own = f"SELECT {d} AS k, n, p AS q FROM tspv JOIN w{d} USING (item_id)"
        out.append(f"s{d} AS ({own})" if not d else f"s{d} AS (SELECT * FROM s{d - 1} UNION ALL {own})")
    return out


def refined(start: str, steps: int) -> list[str]:
    """r0, r1, ...: books after each update of the alternating design; c0, c1, ...: costs of types under them."""
    out = [f"r0 AS (SELECT * FROM {start})"]
    for t in range(steps + 1):
        out.append(f"b{t} AS (SELECT item_id, k, c FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY c, k) AS rn FROM (SELECT item_id, k, sum({PLOGQ}) AS c FROM tspv JOIN r{t} USING (n) GROUP BY item_id, k)) WHERE rn = 1)")
        if t < steps:
            out.append(f"m{t} AS (SELECT k, n, sum(f * p) AS s FROM tspv JOIN b{t} USING (item_id) GROUP BY k, n)")
            out.append(f"r{t + 1} AS (SELECT r.k, r.n, coalesce(m.s / m.t, r.q) AS q FROM r{t} r LEFT JOIN (SELECT *, sum(s) OVER (PARTITION BY k) AS t FROM m{t}) m ON m.k = r.k AND m.n = r.n)")
    return out


def pooled(layout: tuple[int, int, int]) -> list[str]:
    """Types of a two-user problem from vec and ch(item_id, w0, w1, w2), their channels, and the pools of a layout."""
    return [
        "vec AS (SELECT item_id, list(p ORDER BY n) AS v FROM spv GROUP BY item_id)",
        "ptypes AS (SELECT min(item_id) AS item_id, v, sum(w0) AS w0, sum(w1) AS w1, sum(w2) AS w2 FROM vec JOIN ch USING (item_id) GROUP BY v)",
        "pspv AS (SELECT item_id, unnest(range(len(v))) AS n, unnest(v) AS p FROM ptypes)",
        f"pent AS (SELECT item_id, w0, w1, w2, h FROM ptypes JOIN (SELECT item_id, sum({PLOGP}) AS h FROM pspv GROUP BY item_id) USING (item_id))",
        "pch AS (SELECT * FROM (SELECT item_id, 0 AS channel, w0 AS w FROM pent UNION ALL SELECT item_id, 1, w1 FROM pent UNION ALL SELECT item_id, 2, w2 FROM pent) WHERE w > 0)",
        pools(layout, "pools"),
    ]


def pools(layout: tuple[int, int, int], name: str) -> str:
    marks = [pool for pool, size in enumerate(layout) for _ in range(size)]
    return f"{name} AS (SELECT * FROM (VALUES {', '.join(f'({k}, {pool})' for k, pool in enumerate(marks))}) t(k, pool))"


def pool_seeds(layout: tuple[int, int, int], seed: int, x: str = "") -> list[str]:
    """Seeds (k, n, q) of all pools, the common one first: each is drawn by its pool's weight and its gap to the books that serve it."""
    marks = [pool for pool, size in enumerate(layout) for _ in range(size)]
    out = []
    for d, pool in enumerate(marks):
        near = [str(j) for j in range(d) if marks[j] in (0, pool)]
        weight = f"w{pool}" if pool else "(w0 + w1 + w2)"
        source = "pent"
        if near:
            out.append(f"{x}g{d} AS (SELECT item_id, min(c) AS c FROM (SELECT item_id, k, sum({PLOGQ}) AS c FROM pspv JOIN {x}s{d - 1} USING (n) WHERE k IN ({', '.join(near)}) GROUP BY item_id, k) GROUP BY item_id)")
            weight, source = f"CASE WHEN {weight} > 0 THEN {weight} * pow(greatest(0.0, c - h), 2) ELSE 0 END", f"pent JOIN {x}g{d} USING (item_id)"
        u = uniform(f"'{seed}'", "item_id", f"{d + 1}")
        out.append(f"{x}w{d} AS (SELECT arg_min(item_id, [-ln({u}) / weight, item_id::DOUBLE]) AS item_id FROM (SELECT item_id, {weight} AS weight FROM {source}) WHERE weight > 0)")
        own = f"SELECT {d} AS k, n, p AS q FROM pspv JOIN {x}w{d} USING (item_id)"
        out.append(f"{x}s{d} AS ({own})" if not d else f"{x}s{d} AS (SELECT * FROM {x}s{d - 1} UNION ALL {own})")
    return out


def pool_assign(books: str, into: str, pools: str = "pools") -> list[str]:
    """Each channel's rows with the cheapest book that it may use."""
    return [
        f"{into}c AS (SELECT item_id, k, sum({PLOGQ}) AS c FROM pspv JOIN {books} USING (n) GROUP BY item_id, k)",
        f"{into} AS (SELECT item_id, channel, w, k, c FROM (SELECT pch.*, k, c, row_number() OVER (PARTITION BY pch.item_id, channel ORDER BY c, k) AS rn FROM pch JOIN {into}c USING (item_id) JOIN {pools} USING (k) WHERE pool = 0 OR pool = channel) WHERE rn = 1)",
    ]


def pool_means(assigned: str, old: str, into: str) -> str:
    """Books as means of their rows; a book without rows stays as it was."""
    return f"{into} AS (SELECT r.k, r.n, coalesce(m.s / m.t, r.q) AS q FROM {old} r LEFT JOIN (SELECT *, sum(s) OVER (PARTITION BY k) AS t FROM (SELECT k, n, sum(w * p) AS s FROM {assigned} JOIN pspv USING (item_id) GROUP BY k, n)) m ON m.k = r.k AND m.n = r.n)"


def pool_refined(start: str, steps: int, x: str = "", pools: str = "pools") -> list[str]:
    """r0, r1, ...: books after each update; b0, b1, ...: the rows under them."""
    out = [f"{x}r0 AS (SELECT * FROM {start})"]
    for t in range(steps + 1):
        out += pool_assign(f"{x}r{t}", f"{x}b{t}", pools)
        if t < steps:
            out.append(pool_means(f"{x}b{t}", f"{x}r{t}", f"{x}r{t + 1}"))
    return out


def pool_soft(books: int, seed: int, outer: int, inner: int, noise: int) -> list[str]:
    """x0, x1, ...: log shares after each inner step; q: shares by channel; t and y: their sums by book, and by book and symbol."""

    def sums(i: int) -> list[str]:
        return [
            f"p{i} AS (SELECT pch.item_id, channel, w, k, x, pow(2, x - max(x) OVER (PARTITION BY pch.item_id, channel)) AS r FROM pch JOIN x{i} USING (item_id) JOIN pools USING (k) WHERE pool = 0 OR pool = channel)",
            f"q{i} AS (SELECT item_id, channel, w, k, x, r / sum(r) OVER (PARTITION BY item_id, channel) AS r FROM p{i})",
            f"t{i} AS (SELECT k, sum(w * r) AS t FROM q{i} GROUP BY k)",
            f"y{i} AS (SELECT k, n, sum(w * r * p) AS s FROM q{i} JOIN pspv USING (item_id) GROUP BY k, n)",
        ]

    out = [f"x0 AS (SELECT item_id, k, log2({uniform(f"'{seed}'", 'item_id', f'(k + {noise})')}) AS x FROM pent, range({books}) b(k))", *sums(0)]
    step = 0
    for _ in range(outer):
        tangent = step
        for _ in range(inner):
            slope = f"SELECT item_id, k, sum(p * log2(greatest(s, 1e-300))) AS g FROM pspv JOIN y{tangent} USING (n) GROUP BY item_id, k"
            out.append(f"x{step + 1} AS (SELECT x.item_id, x.k, x.x + g.g - log2(greatest(t.t, 1e-300)) AS x FROM x{step} x JOIN t{step} t USING (k) JOIN ({slope}) g ON g.item_id = x.item_id AND g.k = x.k)")
            step += 1
            out += sums(step)
    return out


def with_(*parts: str) -> str:
    return "WITH " + ",\n".join(parts) + "\n"
