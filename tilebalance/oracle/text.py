"""Builders of DuckDB text. Each states a definition again, unrolled where it recurs; none looks at how Spark computes it.

A statement is a list of (name, body) of common table expressions and a last select."""

from __future__ import annotations

Ctes = list[tuple[str, str]]

_M = "((({0}) % {1}) + {1}) % {1}"

#: Domain, then SQL of key, x, y, vx, vy, weight, species, and the table.
_ADAPTERS = {
    "EV": (2592000000000, 65536, "event_id", "epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')", "round(value * 100)::BIGINT", "CASE WHEN event_id % 2 = 0 THEN 1 ELSE -1 END * 10125000000", "(user_id % 7 - 3) * 128", "1", "event_id % 2", "events"),
    "LP": (16777216, 4096, "NULL", "round(l_extendedprice * 100)::BIGINT", "date_diff('day', DATE '1995-01-01', l_shipdate::DATE)", "CASE WHEN l_suppkey % 2 = 0 THEN 1 ELSE -1 END * 65536", "0", "1", "l_suppkey % 2", "lineitem"),
    "LQ": (16777216, 64, "NULL", "round(l_extendedprice * 100)::BIGINT", "l_quantity::BIGINT - 1", "(l_quantity::BIGINT - 25) * 4096", "1", "1", "l_linenumber % 2", "lineitem"),
    "OR": (67108864, 4096, "o_orderkey", "round(o_totalprice * 100)::BIGINT", "date_diff('day', DATE '1995-01-01', o_orderdate::DATE)", "CASE WHEN o_orderkey % 2 = 0 THEN 1 ELSE -1 END * 262144", "1", "1", "o_orderkey % 2", "orders"),
    "EM": (2097152, 2097152, "vec_id", "floor((embedding[1]::DOUBLE + 1) * 1048576)::BIGINT", "floor((embedding[2]::DOUBLE + 1) * 1048576)::BIGINT", "floor(embedding[3]::DOUBLE * 16384)::BIGINT", "floor(embedding[4]::DOUBLE * 16384)::BIGINT", "1", "label % 2", "embeddings"),
    "DOC": (65536, 32, "doc_id", "doc_id * 40503", "regexp_extract(source, '(\\d+)', 1)::BIGINT", "0", "0", "n_chars", "0", "documents"),
    "PG": (65536, 65536, "page_id", "page_id * 40503", "least(length(html), 65535)", "0", "0", "length(html)", "0", "pages"),
    "CV": (65536, 32, "conv_id", "conv_id * 40503", "turn", "0", "0", "length(text)", "0", "conversations"),
}


def join(ctes: Ctes, last: str) -> str:
    return "WITH " + ",\n".join(f"{name} AS MATERIALIZED ({body})" for name, body in ctes) + "\n" + last


def domain(adapter: str) -> tuple[int, int]:
    return _ADAPTERS[adapter][:2]


def mod(a: str, b) -> str:
    return _M.format(a, b)


def particles(adapter: str, t: int | str = 0) -> str:
    lx, ly, key, x, y, vx, vy, w, s, table = _ADAPTERS[adapter]
    start = f"SELECT {key} AS pid_key, {mod(x, lx)} AS x, {mod(y, ly)} AS y, {vx} AS vx, {vy} AS vy, {w} AS weight, {s} AS species FROM {table}"
    return f"SELECT pid_key::BIGINT AS pid_key, ({mod(f'x + {t} * vx', lx)})::BIGINT AS x, ({mod(f'y + {t} * vy', ly)})::BIGINT AS y, vx::BIGINT AS vx, vy::BIGINT AS vy, weight::BIGINT AS weight, species::BIGINT AS species FROM ({start})"


def tile(adapter: str, n: int, m: int) -> tuple[str, str]:
    lx, ly = domain(adapter)
    return f"(x * {n}) // {lx}", f"(y * {m}) // {ly}"


def loads(tag: str, adapter: str, n: int, m: int, t: int = 0, cost: str = "count(*)") -> Ctes:
    ti, tj = tile(adapter, n, m)
    return [(f"p{tag}", particles(adapter, t)), (f"l{tag}", f"SELECT {ti} AS ti, {tj} AS tj, ({cost})::BIGINT AS cost FROM p{tag} GROUP BY 1, 2")]


def prefix(tag: str, n: int, m: int) -> Ctes:
    """Dense costs d and prefix sums s of l."""
    dense = f"SELECT i AS ti, j AS tj, coalesce(cost, 0) AS cost FROM range({n}) a(i) CROSS JOIN range({m}) b(j) LEFT JOIN l{tag} l ON l.ti = i AND l.tj = j"
    rows = f"SELECT ti, tj, sum(cost) OVER (PARTITION BY ti ORDER BY tj) AS r FROM d{tag}"
    whole = f"SELECT ti + 1 AS i, tj + 1 AS j, (sum(r) OVER (PARTITION BY tj ORDER BY ti))::BIGINT AS s FROM ({rows}) UNION ALL SELECT i, 0, 0 FROM range({n + 1}) a(i) UNION ALL SELECT 0, j, 0 FROM range(1, {m + 1}) b(j)"
    return [(f"d{tag}", dense), (f"s{tag}", whole)]


def _box(tag: str, c: str, x0: str, x1: str, y0: str, y1: str, k: str) -> tuple[str, str]:
    """Expression and joins of the cost of a box."""
    names = [f"{k}{i}" for i in range(4)]
    corners = [(x1, y1), (x1, y0), (x0, y1), (x0, y0)]
    joins = " ".join(f"JOIN s{tag} {a} ON {a}.i = {x} AND {a}.j = {y}" for a, (x, y) in zip(names, corners, strict=True))
    return f"({names[0]}.s - {names[1]}.s - {names[2]}.s + {names[3]}.s)", joins


def share(tag: str, n: int, m: int, parts: int, first: str = "x", rule: str = "alternate", by: str = "cost", tolerance: float = 0.25, out: str = "", old: str = "", frozen: int = 0) -> Ctes:
    """Leaves v and inner nodes n of the proportional cut, level by level; old: the names' suffix of a former tree."""
    o = out or tag
    got: Ctes = [(f"c{o}_0", f"SELECT 1::BIGINT AS node, 0::BIGINT AS depth, 0::BIGINT AS x0, {n}::BIGINT AS x1, 0::BIGINT AS y0, {m}::BIGINT AS y1, 0::BIGINT AS p_first, {parts}::BIGINT AS p, '{first}' AS dim, s AS load FROM s{tag} WHERE i = {n} AND j = {m}")]
    levels = max(1, (parts - 1).bit_length()) if rule != "aspect" else max(1, parts - 1)
    for k in range(levels):
        c = f"c{o}_{k}"
        split = "CROSS JOIN range(1, c.p) g(pl)" if rule == "aspect" else "CROSS JOIN (SELECT 1) g(one)"
        pl = "g.pl" if rule == "aspect" else "(c.p // 2)"
        want = "CASE WHEN c.x1 - c.x0 > c.y1 - c.y0 THEN 'x' WHEN c.x1 - c.x0 < c.y1 - c.y0 THEN 'y' ELSE c.dim END" if rule == "longest" else "c.dim"
        sides = []
        for d, a, b, lo, hi in (("x", "x0", "x1", "y0", "y1"), ("y", "y0", "y1", "x0", "x1")):
            q = "u.q"
            expr, joins = _box(tag, c, f"c.{a}", q, f"c.{lo}", f"c.{hi}", "z") if d == "x" else _box(tag, c, f"c.{lo}", f"c.{hi}", f"c.{a}", q, "z")
            error = f"abs({expr} * c.p - c.load * {pl})" if by == "cost" else f"abs((u.q - c.{a}) * c.p - (c.{b} - c.{a}) * {pl})"
            shape = lambda u, w: f"greatest({u}, {w})::DOUBLE / least({u}, {w})"
            worst = f"greatest({shape(f'(u.q - c.{a})', f'(c.{hi} - c.{lo})')}, {shape(f'(c.{b} - u.q)', f'(c.{hi} - c.{lo})')})"
            sides.append(
                f"SELECT c.*, '{d}' AS d, u.q AS q, {pl} AS pl, {expr} AS left_load, ('{d}' <> {want})::INT AS off, {error} AS error, round({worst}, 9) AS worst FROM {c} c {split} CROSS JOIN LATERAL (SELECT unnest(range(c.{a} + 1, c.{b})) AS q) u {joins} "
                f"WHERE c.p > 1 AND (u.q - c.{a}) * (c.{hi} - c.{lo}) >= {pl} AND (c.{b} - u.q) * (c.{hi} - c.{lo}) >= c.p - {pl}"
            )
        body = " UNION ALL ".join(sides)
        moved, keep = "0", ""
        if old:
            body = f"SELECT k.*, e.cut AS was, e.d AS was_d FROM ({body}) k LEFT JOIN n{old} e ON e.node = k.node"
            moved = "CASE WHEN was_d = d THEN abs(q - was) ELSE 0 END"
            keep = f"WHERE NOT (depth < {frozen} AND was IS NOT NULL AND (was <> q OR was_d <> d))"
        if rule == "aspect":
            # the best line of each split first, then the split
            body = f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY node, off, pl ORDER BY error, {moved}, q) AS r1 FROM ({body})) WHERE r1 = 1"
            far = f"(error > {tolerance} * load)"
            order = f"off, {far}::INT, CASE WHEN {far} THEN 0 ELSE worst END, CASE WHEN {far} THEN error ELSE 0 END, abs(2 * pl - p), pl"
        else:
            order = f"off, error, {moved}, q"
        got.append((f"b{o}_{k}", f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY {order}) AS best FROM ({body}) {keep}) WHERE best = 1"))
        flip = "CASE WHEN d = 'x' THEN 'y' ELSE 'x' END"
        left = f"SELECT 2 * node AS node, depth + 1 AS depth, x0, CASE WHEN d = 'x' THEN q ELSE x1 END AS x1, y0, CASE WHEN d = 'y' THEN q ELSE y1 END AS y1, p_first, pl AS p, {flip} AS dim, left_load AS load FROM b{o}_{k}"
        right = f"SELECT 2 * node + 1, depth + 1, CASE WHEN d = 'x' THEN q ELSE x0 END, x1, CASE WHEN d = 'y' THEN q ELSE y0 END, y1, p_first + pl, p - pl, {flip}, load - left_load FROM b{o}_{k}"
        got.append((f"c{o}_{k + 1}", f"{left} UNION ALL {right}"))
    ends = " UNION ALL ".join(f"SELECT * FROM c{o}_{k} WHERE p = 1" for k in range(levels + 1))
    got.append((f"v{o}", f"SELECT p_first AS pid, x0, x1, y0, y1, depth AS height, load::BIGINT AS load FROM ({ends})"))
    inner = " UNION ALL ".join(f"SELECT node, depth, d, q AS cut, x0, x1, y0, y1, p_first, p FROM b{o}_{k}" for k in range(levels))
    got.append((f"n{o}", inner))
    return got


def tether_leaves(tag: str, old: str, out: str, depth: int) -> Ctes:
    """Leaves v of the old tree when all cuts at its deepest level, depth, move by the costs of tag."""
    sides = []
    for d, a, b, lo, hi in (("x", "x0", "x1", "y0", "y1"), ("y", "y0", "y1", "x0", "x1")):
        box = lambda q: (f"e.{a}", q, f"e.{lo}", f"e.{hi}") if d == "x" else (f"e.{lo}", f"e.{hi}", f"e.{a}", q)  # noqa: E731, B023
        one, j1 = _box(tag, "e", *box("u.q"), "y")
        two, j2 = _box(tag, "e", *box(f"e.{b}"), "z")
        sides.append(
            f"SELECT e.*, u.q AS q, {one} AS left_load, {two} AS load FROM n{old} e CROSS JOIN LATERAL (SELECT unnest(range(e.{a} + 1, e.{b})) AS q) u {j1} {j2} "
            f"WHERE e.depth = {depth} AND e.d = '{d}' AND ((u.q - e.{a}) * (e.{hi} - e.{lo}) >= e.p // 2 AND (e.{b} - u.q) * (e.{hi} - e.{lo}) >= e.p - e.p // 2 OR u.q = e.cut)"
        )
    best = f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY abs(left_load * p - load * (p // 2)), abs(q - cut), q) AS best FROM ({' UNION ALL '.join(sides)})) WHERE best = 1"
    left = f"SELECT p_first AS pid, x0, CASE WHEN d = 'x' THEN q ELSE x1 END AS x1, y0, CASE WHEN d = 'y' THEN q ELSE y1 END AS y1, depth + 1 AS height, left_load::BIGINT AS load FROM b{out}"
    right = f"SELECT p_first + 1, CASE WHEN d = 'x' THEN q ELSE x0 END, x1, CASE WHEN d = 'y' THEN q ELSE y0 END, y1, depth + 1, (load - left_load)::BIGINT FROM b{out}"
    return [(f"b{out}", best), (f"v{out}", f"{left} UNION ALL {right}")]


def even(out: str, n: int, m: int, columns: int, rows: int) -> Ctes:
    return [(f"v{out}", f"SELECT (c * {rows} + r)::BIGINT AS pid, ({n} * c // {columns})::BIGINT AS x0, ({n} * (c + 1) // {columns})::BIGINT AS x1, ({m} * r // {rows})::BIGINT AS y0, ({m} * (r + 1) // {rows})::BIGINT AS y1, 0::BIGINT AS height FROM range({columns}) a(c) CROSS JOIN range({rows}) b(r)")]


def reload(tag: str, boxes: str, out: str) -> Ctes:
    """Boxes v with the costs of tag."""
    expr, joins = _box(tag, "v", "v.x0", "v.x1", "v.y0", "v.y1", "z")
    return [(f"v{out}", f"SELECT v.pid, v.x0, v.x1, v.y0, v.y1, v.height, {expr}::BIGINT AS load FROM v{boxes} v {joins}")]


def strips(tag: str, n: int, m: int, rows: list[int], first: str = "x", out: str = "") -> Ctes:
    """Leaves v, column borders x(k, q) and row borders r(c, k, q) of strips."""
    o, wide, deep, pc, whole = out or tag, n if first == "x" else m, m if first == "x" else n, len(rows), sum(rows)
    i, j = ("i", "j") if first == "x" else ("j", "i")
    goals = ", ".join(f"({k}, {sum(rows[:k])})" for k in range(1, pc)) or "(NULL, NULL)"
    sizes = ", ".join(f"({c}, {r}, {sum(rows[:c])})" for c, r in enumerate(rows))
    run = f"SELECT {i} AS q, s FROM s{tag} WHERE {j} = {deep}"
    total = f"(SELECT s FROM s{tag} WHERE i = {n} AND j = {m})"
    best = f"SELECT k, q AS b FROM (SELECT g.k, w.q, row_number() OVER (PARTITION BY g.k ORDER BY abs(w.s * {whole} - {total} * g.upto), w.q) AS best FROM (VALUES {goals}) g(k, upto) CROSS JOIN ({run}) w WHERE g.k IS NOT NULL) WHERE best = 1"
    fixed = f"SELECT k, least(greatest(max(b - k) OVER (ORDER BY k) + k, k), {wide} - ({pc} - k)) AS q FROM ({best})"
    got: Ctes = [(f"x{o}", f"SELECT k::BIGINT AS k, q::BIGINT AS q FROM ({fixed}) UNION ALL SELECT 0, 0 UNION ALL SELECT {pc}, {wide}")]
    got.append((f"k{o}", f"SELECT a.k AS c, a.q AS a, b.q AS b, z.size, z.base FROM x{o} a JOIN x{o} b ON b.k = a.k + 1 JOIN (VALUES {sizes}) z(c, size, base) ON z.c = a.k"))
    column = f"SELECT c.c, c.size, w.{j} AS q, (w.s - v.s)::BIGINT AS s FROM k{o} c JOIN s{tag} w ON w.{i} = c.b JOIN s{tag} v ON v.{i} = c.a AND v.{j} = w.{j}"
    got.append((f"w{o}", column))
    best = f"SELECT c, size, k, q AS b FROM (SELECT w.c, w.size, g.k, w.q, row_number() OVER (PARTITION BY w.c, g.k ORDER BY abs(w.s * w.size - t.s * g.k), w.q) AS best FROM w{o} w JOIN w{o} t ON t.c = w.c AND t.q = {deep} CROSS JOIN LATERAL (SELECT unnest(range(1, w.size)) AS k) g) WHERE best = 1"
    fixed = f"SELECT c, k, least(greatest(max(b - k) OVER (PARTITION BY c ORDER BY k) + k, k), {deep} - (size - k)) AS q FROM ({best})"
    got.append((f"r{o}", f"SELECT c, k::BIGINT AS k, q::BIGINT AS q FROM ({fixed}) UNION ALL SELECT c, 0, 0 FROM k{o} UNION ALL SELECT c, size, {deep} FROM k{o}"))
    return got + strip_leaves(tag, o, first)


def strip_leaves(tag: str, o: str, first: str = "x", height: int = 2) -> Ctes:
    box = "c.a AS x0, c.b AS x1, a.q AS y0, b.q AS y1" if first == "x" else "a.q AS x0, b.q AS x1, c.a AS y0, c.b AS y1"
    raw = f"SELECT (c.base + a.k)::BIGINT AS pid, {box}, {height}::BIGINT AS height FROM k{o} c JOIN r{o} a ON a.c = c.c JOIN r{o} b ON b.c = c.c AND b.k = a.k + 1"
    return [(f"vv{o}", raw), *reload(tag, f"v{o}", o)]


def strip_step(tag: str, before: str, out: str, t: int, n: int, m: int, columns: bool = False) -> Ctes:
    """Borders and leaves after step t from those before, first dimension x."""
    old = f"SELECT b.c, b.k, b.q, a.q AS lo, d.q AS hi, c.size FROM r{before} b JOIN k{before} c ON c.c = b.c JOIN r{before} a ON a.c = b.c AND a.k = b.k - 1 JOIN r{before} d ON d.c = b.c AND d.k = b.k + 1"
    acts = f"((size = 2) OR ((k - 1) % 2 = {(t + 1) % 2}))"
    lines = f"SELECT c.c, w.j AS q, (w.s - v.s)::BIGINT AS s FROM k{before} c JOIN s{tag} w ON w.i = c.b JOIN s{tag} v ON v.i = c.a AND v.j = w.j"
    found = f"SELECT o.c, o.k, u.q, row_number() OVER (PARTITION BY o.c, o.k ORDER BY abs(2 * (u.s - l.s) - (h.s - l.s)), abs(u.q - o.q), u.q) AS best FROM o{out} o JOIN w{out} u ON u.c = o.c AND u.q > o.lo AND u.q < o.hi JOIN w{out} l ON l.c = o.c AND l.q = o.lo JOIN w{out} h ON h.c = o.c AND h.q = o.hi WHERE {acts}"
    got: Ctes = [(f"o{out}", old), (f"w{out}", lines), (f"f{out}", f"SELECT c, k, q FROM ({found}) WHERE best = 1")]
    got.append((f"r{out}", f"SELECT r.c, r.k, coalesce(f.q, r.q) AS q FROM r{before} r LEFT JOIN f{out} f ON f.c = r.c AND f.k = r.k"))
    if not columns:
        got.append((f"k{out}", f"SELECT * FROM k{before}"))
    else:
        pair = f"SELECT a.c, a.b AS q, a.a AS lo, b.b AS hi, a.size AS ra, a.size + b.size AS rs FROM k{before} a JOIN k{before} b ON b.c = a.c + 1 WHERE (SELECT count(*) FROM k{before}) = 2 OR a.c % 2 = 0"
        found = f"SELECT o.c, u.i AS q, row_number() OVER (PARTITION BY o.c ORDER BY abs((u.s - l.s) * o.rs - (h.s - l.s) * o.ra), abs(u.i - o.q), u.i) AS best FROM ({pair}) o JOIN s{tag} u ON u.j = {m} AND u.i > o.lo AND u.i < o.hi JOIN s{tag} l ON l.j = {m} AND l.i = o.lo JOIN s{tag} h ON h.j = {m} AND h.i = o.hi"
        got.append((f"g{out}", f"SELECT c, q FROM ({found}) WHERE best = 1"))
        got.append((f"k{out}", f"SELECT k.c, coalesce(l.q, k.a) AS a, coalesce(r.q, k.b) AS b, k.size, k.base FROM k{before} k LEFT JOIN g{out} l ON l.c = k.c - 1 LEFT JOIN g{out} r ON r.c = k.c"))
    return got + strip_leaves(tag, out)


def imbalance_of(v: str) -> str:
    return f"SELECT max(load)::BIGINT AS max_load, round(avg(load), 6) AS mean_load, round(max(load) / avg(load), 6) AS imbalance FROM v{v}"


def owner_join(p: str, v: str, adapter: str, n: int, m: int, alias: str = "v") -> str:
    """Join of particles p, aliased p, with the boxes that contain them."""
    lx, ly = domain(adapter)
    return f"JOIN v{v} {alias} ON (p.x * {n}) // {lx} >= {alias}.x0 AND (p.x * {n}) // {lx} < {alias}.x1 AND (p.y * {m}) // {ly} >= {alias}.y0 AND (p.y * {m}) // {ly} < {alias}.y1"
