"""Queries of the methods: phases, cuts, diffusion, placement, runs and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import diffusion, fields, mesh, metrics, partition, pic, placement
from ..operators.cost import LoadMap, gather, tile_load
from ..operators.grid import Grid, locate, tile_x, tile_y, tiles
from ..oracle import text as o
from ..sources.tables import grid_of, json_weight, load, particles, events_particles
from .registry import query

LEAVES = "SELECT pid, x0, x1, y0, y1, height, load FROM v"


def at(spark: SparkSession, sf: str, adapter: str = "EV", t: int = 0, n: int = 32) -> DataFrame:
    """Particles after t steps of drift."""
    df = particles(spark, sf, adapter)
    return pic.push(df, grid_of(adapter, n), t) if t else df


def costs(spark: SparkSession, sf: str, adapter: str = "EV", n: int = 32, t: int = 0, weight: str | None = None) -> LoadMap:
    grid = grid_of(adapter, n)
    return gather(tile_load(at(spark, sf, adapter, t, n), grid, weight=weight), grid)


def _loads(adapter="EV", n=32, t=0, tag="", cost="count(*)"):
    return o.loads(tag, adapter, n, n, t, cost) + o.prefix(tag, n, n)


# phases

_T, _J = o.tile("EV", 32, 32)


@query("pic_locate", o.join([("p", o.particles("EV"))], f"SELECT pid_key, x, y, {_T} AS ti, {_J} AS tj FROM p"))
def pic_locate(spark, sf):
    return locate(particles(spark, sf, "EV"), grid_of("EV")).select("pid_key", "x", "y", "ti", "tj")


@query("pic_locate_elements_quad", o.join([("p", o.particles("EV"))], "SELECT pid_key, (((x * 16) // 2592000000000) * 16 + (y * 16) // 65536) * 2 AS elem FROM p"))
def pic_locate_elements_quad(spark, sf):
    return mesh.locate_quads(particles(spark, sf, "EV"), 16, grid_of("EV")).select("pid_key", "elem")


def _vertices(k: int, lx: int, ly: int, jitter: bool) -> str:
    qx, qy = max(1, lx // k // 4), max(1, ly // k // 4)
    inner = f"(i > 0 AND i < {k} AND j > 0 AND j < {k})"
    dx, dy = (f"CASE WHEN {inner} THEN (i * {a} + j * {b}) % {2 * q - 1} - {q - 1} ELSE 0 END" if jitter else "0" for a, b, q in ((7919, 104729, qx), (15485863, 32452843, qy)))
    return f"SELECT i, j, (i * {lx}) // {k} + {dx} AS x, (j * {ly}) // {k} + {dy} AS y FROM range({k + 1}) a(i) CROSS JOIN range({k + 1}) b(j)"


def mesh_sql(kind: str, k: int, lx: int, ly: int) -> list[tuple[str, str]]:
    """Elements e (elem, kind) and their corners q (elem, c, x, y)."""
    half = {"quads": "true", "triangles": "false", "hybrid": f"i < {k // 2}"}[kind]
    cell = f"SELECT i, j, (i * {k} + j) * 2 AS base, {half} AS quad FROM range({k}) a(i) CROSS JOIN range({k}) b(j)"
    shapes = [("quad", 0, [(0, 0), (1, 0), (1, 1), (0, 1)]), ("NOT quad", 0, [(0, 0), (1, 0), (1, 1)]), ("NOT quad", 1, [(0, 0), (1, 1), (0, 1)])]
    corner = " UNION ALL ".join(f"SELECT base + {part} AS elem, quad, {c} AS c, i + {a} AS i, j + {b} AS j FROM cell WHERE {when}" for when, part, vs in shapes for c, (a, b) in enumerate(vs))
    return [("vx", _vertices(k, lx, ly, kind == "triangles")), ("cell", cell), ("q", f"SELECT u.elem, u.quad, u.c, v.x, v.y FROM ({corner}) u JOIN vx v USING (i, j)"), ("e", "SELECT elem, CASE WHEN quad THEN 'quad' ELSE 'tri' END AS kind, sum(x)::BIGINT // count(*) AS bx, sum(y)::BIGINT // count(*) AS cy FROM q GROUP BY elem, quad")]


@query(
    "pic_locate_elements_tri",
    o.join(
        [*mesh_sql("triangles", 8, 2592000000000, 65536), ("p", o.particles("EV")), ("s", "SELECT a.elem, a.x AS ax, a.y AS ay, b.x AS cx, b.y AS cy FROM q a JOIN q b ON b.elem = a.elem AND b.c = (a.c + 1) % 3")],
        "SELECT pid_key, min(elem)::BIGINT AS elem FROM (SELECT pid_key, elem FROM p JOIN s ON (cx - ax)::DOUBLE * (y - ay) - (cy - ay)::DOUBLE * (x - ax) >= 0 GROUP BY pid_key, elem HAVING count(*) = 3) GROUP BY pid_key",
    ),
)
def pic_locate_elements_tri(spark, sf):
    grid = grid_of("EV", 16)
    return mesh.locate_elements(particles(spark, sf, "EV"), mesh.triangles(spark, 8, grid), grid).select("pid_key", "elem")


@query("mesh_barycentre_tiles", o.join([("p", "SELECT p_partkey AS elem, p_size AS bx, (((round(p_retailprice * 100)::BIGINT - 90000) % 16384) + 16384) % 16384 AS cy FROM part")], "SELECT elem, (bx * 32) // 64 AS ti, (cy * 32) // 16384 AS tj FROM p"))
def mesh_barycentre_tiles(spark, sf):
    return mesh.assign_tiles(mesh.part_elements(load(spark, sf, "part")), Grid(32, 32, 64, 16_384)).select("elem", "ti", "tj")


_FLOWS = "sum(weight)::BIGINT AS charge, sum(weight * vx)::BIGINT AS jx, sum(weight * vy)::BIGINT AS jy"


@query("pic_deposit_tile", o.join([("p", o.particles("EV"))], f"SELECT {_T} AS ti, {_J} AS tj, {_FLOWS} FROM p GROUP BY 1, 2"))
def pic_deposit_tile(spark, sf):
    return pic.deposit(particles(spark, sf, "EV"), grid_of("EV"))


@query("pic_deposit_element", o.join([("p", o.particles("EV"))], f"SELECT (((x * 16) // 2592000000000) * 16 + (y * 16) // 65536) * 2 AS elem, {_FLOWS} FROM p GROUP BY 1"))
def pic_deposit_element(spark, sf):
    grid = grid_of("EV")
    return pic.deposit(mesh.locate_quads(particles(spark, sf, "EV"), 16, grid), grid, "element")


@query(
    "pic_deposit_node",
    o.join(
        [
            ("p", o.particles("EV")),
            ("r", f"SELECT *, {_T} AS i, {_J} AS j, (((x * 32) % 2592000000000) * 256) // 2592000000000 AS u, (((y * 32) % 65536) * 256) // 65536 AS v FROM p"),
            ("c", "SELECT (i + a) % 32 AS ti, (j + b) % 32 AS tj, (CASE WHEN a = 1 THEN u ELSE 256 - u END) * (CASE WHEN b = 1 THEN v ELSE 256 - v END) AS share, weight, vx, vy FROM r CROSS JOIN (VALUES (0, 0), (0, 1), (1, 0), (1, 1)) s(a, b)"),
        ],
        "SELECT ti, tj, sum(weight * share)::BIGINT AS charge, sum(weight * share * vx)::BIGINT AS jx, sum(weight * share * vy)::BIGINT AS jy FROM c GROUP BY 1, 2",
    ),
)
def pic_deposit_node(spark, sf):
    return pic.deposit(particles(spark, sf, "EV"), grid_of("EV"), "node")


def gradient_sql(p: str, out: str, n: int = 32) -> list[tuple[str, str]]:
    """(ti, tj, fx, fy) f from particles p, for the tiles beside charged ones."""
    d = f"SELECT {_T} AS ti, {_J} AS tj, sum(weight)::BIGINT AS c FROM {p} GROUP BY 1, 2"
    sides = " UNION ALL ".join(f"SELECT (ti + {a} + {n}) % {n} AS ti, (tj + {b} + {n}) % {n} AS tj, {fx} AS fx, {fy} AS fy FROM d{out}" for a, b, fx, fy in ((1, 0, "c", "0"), (-1, 0, "-c", "0"), (0, 1, "0", "c"), (0, -1, "0", "-c")))
    return [(f"d{out}", d), (f"f{out}", f"SELECT ti, tj, sum(fx)::BIGINT AS fx, sum(fy)::BIGINT AS fy FROM ({sides}) GROUP BY 1, 2")]


@query("pic_field_gradient", o.join([("p", o.particles("EV")), *gradient_sql("p", "")], "SELECT ti, tj, fx, fy FROM f"))
def pic_field_gradient(spark, sf):
    grid = grid_of("EV")
    return fields.tile_gradient(pic.deposit(particles(spark, sf, "EV"), grid), grid)


@query("pic_interpolate", o.join([("p", o.particles("EV")), *gradient_sql("p", "")], f"SELECT p.pid_key, coalesce(f.fx, 0) AS fx, coalesce(f.fy, 0) AS fy FROM p LEFT JOIN f ON f.ti = {_T} AND f.tj = {_J}"))
def pic_interpolate(spark, sf):
    grid, df = grid_of("EV"), particles(spark, sf, "EV")
    return pic.interpolate(df, fields.tile_gradient(pic.deposit(df, grid), grid), grid).select("pid_key", "fx", "fy")


for _t in (1, 50):

    @query(f"pic_push_t{_t}", o.join([("p", o.particles("EV", _t))], "SELECT pid_key, x, y FROM p"))
    def pic_push(spark, sf, t=_t):
        return at(spark, sf, "EV", t).select("pid_key", "x", "y")


def _walls(c: str, size: int) -> str:
    return f"CASE WHEN {o.mod(c, 2 * size)} < {size} THEN {o.mod(c, 2 * size)} ELSE {2 * size - 1} - {o.mod(c, 2 * size)} END"


@query("pic_push_reflect", o.join([("p", o.particles("EV"))], f"SELECT pid_key, {_walls('(x + 50 * vx)', 2592000000000)} AS x, {_walls('(y + 50 * vy)', 65536)} AS y, CASE WHEN {o.mod('(x + 50 * vx)', 2 * 2592000000000)} >= 2592000000000 THEN -vx ELSE vx END AS vx, CASE WHEN {o.mod('(y + 50 * vy)', 2 * 65536)} >= 65536 THEN -vy ELSE vy END AS vy FROM p"))
def pic_push_reflect(spark, sf):
    return pic.push(particles(spark, sf, "EV"), grid_of("EV", boundary="reflect"), 50).select("pid_key", "x", "y", "vx", "vy")


@query("pic_push_absorb", o.join([("p", o.particles("EV"))], "SELECT pid_key, x + 50 * vx AS x, y + 50 * vy AS y FROM p WHERE x + 50 * vx BETWEEN 0 AND 2592000000000 - 1 AND y + 50 * vy BETWEEN 0 AND 65535"))
def pic_push_absorb(spark, sf):
    return pic.push(particles(spark, sf, "EV"), grid_of("EV", boundary="absorb"), 50).select("pid_key", "x", "y")


@query("pic_push_magnetic", o.join([("p", o.particles("EV"))], f"SELECT pid_key, {o.mod('x + round(cos(0.5) * vx + sin(0.5) * vy)::BIGINT', 2592000000000)} AS x, {o.mod('y + round(cos(0.5) * vy - sin(0.5) * vx)::BIGINT', 65536)} AS y FROM p"))
def pic_push_magnetic(spark, sf):
    return pic.push(particles(spark, sf, "EV"), grid_of("EV"), magnetic=0.5).select("pid_key", "x", "y")


def kicks(start: str, steps: int, lx: int, ly: int, n: int = 32, scale: str = "") -> list[tuple[str, str]]:
    got = [("k0", start)]
    for s in range(steps):
        got += gradient_sql(f"k{s}", str(s), n)
        kicked = f"SELECT pid_key, x, y, vx + CASE WHEN species = 0 THEN 1 ELSE -1 END * coalesce(fx, 0) AS vx, vy + CASE WHEN species = 0 THEN 1 ELSE -1 END * coalesce(fy, 0) AS vy, weight, species FROM k{s} p LEFT JOIN f{s} f ON f.ti = {_T} AND f.tj = {_J}"
        got.append((f"k{s + 1}", f"SELECT pid_key, ({o.mod('x + vx', lx)})::BIGINT AS x, ({o.mod('y + vy', ly)})::BIGINT AS y, vx, vy, weight, species FROM ({kicked})"))
    return got


@query("pic_step_kick_3", o.join(kicks(o.particles("EV"), 3, 2592000000000, 65536), "SELECT pid_key, x, y, vx, vy FROM k3"))
def pic_step_kick_3(spark, sf):
    grid, df = grid_of("EV"), particles(spark, sf, "EV")
    for _ in range(3):
        df = pic.step(df, grid)
    return df.select("pid_key", "x", "y", "vx", "vy")


_N = 16


def _leap(steps: int) -> list[tuple[str, str]]:
    n = _N
    got = [
        ("p", o.particles("EV")),
        ("j", f"SELECT i AS ti, k AS tj, coalesce(jx, 0) / 1e10 AS jx, coalesce(jy, 0) / 1e10 AS jy FROM range({n}) a(i) CROSS JOIN range({n}) b(k) LEFT JOIN (SELECT (x * {n}) // 2592000000000 AS ti, (y * {n}) // 65536 AS tj, sum(vx)::BIGINT AS jx, sum(vy)::BIGINT AS jy FROM p GROUP BY 1, 2) d ON d.ti = i AND d.tj = k"),
        ("g0", "SELECT ti, tj, 0.0::DOUBLE AS ex, 0.0::DOUBLE AS ey, 0.0::DOUBLE AS bz FROM j"),
    ]
    for s in range(steps):
        near = lambda a, b, g: f"LEFT JOIN {g} q{a}{b} ON q{a}{b}.ti = (g.ti + {a}) % {n} AND q{a}{b}.tj = (g.tj + {b}) % {n}"
        got.append((f"h{s}", f"SELECT g.ti, g.tj, g.ex, g.ey, g.bz - 0.25 * (q10.ey - g.ey - q01.ex + g.ex) AS bz FROM g{s} g {near(1, 0, f'g{s}')} {near(0, 1, f'g{s}')}"))
        got.append((f"g{s + 1}", f"SELECT g.ti, g.tj, g.ex + 0.25 * (g.bz - q0{n - 1}.bz - j.jx) AS ex, g.ey + 0.25 * (q{n - 1}0.bz - g.bz - j.jy) AS ey, g.bz FROM h{s} g {near(0, n - 1, f'h{s}')} {near(n - 1, 0, f'h{s}')} JOIN j ON j.ti = g.ti AND j.tj = g.tj"))
    return got


@query("pic_leapfrog_quads", o.join(_leap(2), "SELECT ti, tj, round(ex, 6) AS ex, round(ey, 6) AS ey, round(bz, 6) AS bz FROM g2"))
def pic_leapfrog_quads(spark, sf):
    grid = grid_of("EV", _N)
    j = pic.deposit(particles(spark, sf, "EV"), grid).select("ti", "tj", (F.col("jx") / 1e10).alias("jx"), (F.col("jy") / 1e10).alias("jy"))
    start = tiles(spark, grid).select("ti", "tj", *[F.lit(0.0).alias(c) for c in ("ex", "ey", "bz")])
    done = fields.leapfrog_quads(start, j, grid, 0.25, 2)
    return done.select("ti", "tj", *[(F.round(c, 6) + 0.0).alias(c) for c in ("ex", "ey", "bz")])


@query("pic_leapfrog_mesh")
def pic_leapfrog_mesh(spark, sf):
    """Rows only: the field's energy stays within its bound; see the tests. Faces begin with the number of particles in them."""
    grid = grid_of("EV", 8)
    faces = mesh.hybrid(spark, 8, grid)
    inc = mesh.incidence(faces)
    held = mesh.locate_elements(particles(spark, sf, "EV"), faces, grid).groupBy("elem").agg(F.count("*").alias("n"))
    e = inc.select("edge").distinct().select("edge", (F.pmod("edge", F.lit(7)) / 7.0).alias("e"), F.lit(1.0).alias("weight"))
    b = faces.join(held, "elem", "left").select("elem", F.coalesce(F.col("n").cast("double"), F.lit(0.0)).alias("b"), F.lit(1.0).alias("area"))
    return fields.leapfrog_mesh(e, b, inc, 0.25, 2).select("kind", "id", F.round("value", 6).alias("value"))


# cuts


@query("part_even_tiles", o.join(_loads() + o.even("", 32, 32, 4, 2), "SELECT i AS ti, j AS tj, pid, coalesce(cost, 0) AS cost FROM v, LATERAL (SELECT unnest(range(x0, x1)) AS i) a, LATERAL (SELECT unnest(range(y0, y1)) AS j) b LEFT JOIN l ON l.ti = i AND l.tj = j"))
def part_even_tiles(spark, sf):
    """Every tile with its owner and the particles in it."""
    grid = grid_of("EV")
    return partition.even_owner(spark, grid, 4, 2).join(tile_load(particles(spark, sf, "EV"), grid), ["ti", "tj"], "left").select("ti", "tj", "pid", F.coalesce("cost", F.lit(0)).alias("cost"))


def _cut(name: str, adapter: str = "EV", n: int = 32, parts: int = 8, weight: str | None = None, cost: str = "count(*)", halving: bool = False, **how):
    sql = {"first": how.get("first_dim", "x"), "rule": how.get("rule", "alternate"), "by": how.get("by", "cost")}

    @query(name, o.join(_loads(adapter, n, 0, "", cost) + o.share("", n, n, parts, **sql), LEAVES))
    def run(spark, sf):
        loads = costs(spark, sf, adapter, n, weight=weight)
        cut = partition.halving(loads, parts, **how) if halving else partition.share_cut(loads, parts, **how)
        return cut.frame(spark)


_cut("part_share_p5", parts=5)
_cut("part_share_p8")
_cut("part_share_p32", n=128, parts=32)
_cut("part_share_ydim", first_dim="y")
_cut("part_share_longest", adapter="LQ", parts=7, rule="longest")
_cut("part_share_aspect", parts=5, rule="aspect")
_cut("part_share_dichotomy", search="dichotomy")
_cut("part_halving_p8", halving=True)
_cut("part_halving_lp", adapter="LP", parts=16, halving=True)
_cut("part_halving_extent", by="extent", halving=True)
_cut("docs_share_cut", adapter="DOC", weight="weight", cost="sum(weight)")
_cut("part_share_or", adapter="OR", parts=6)
_cut("part_share_em", adapter="EM", parts=3)

_K = "CASE WHEN json_extract_string(props, '$.k') IS NULL THEN NULL ELSE json_extract_string(props, '$.k')::BIGINT END"


@query("part_share_levels", o.join(_loads() + o.share("", 32, 32, 8), LEAVES))
def part_share_levels(spark, sf):
    """The level-wise engine: no tile comes to the driver."""
    from ..operators.lineage import shared

    shared(spark)
    grid = grid_of("EV")
    return partition.share_cut_levels(tile_load(particles(spark, sf, "EV"), grid), grid, 8)


_WEIGHTED = o.particles("EV").replace("1 AS weight", f"{_K} AS weight")


@query("part_share_weighted", o.join([("p", _WEIGHTED), ("l", f"SELECT {_T} AS ti, {_J} AS tj, sum(weight)::BIGINT AS cost FROM p GROUP BY 1, 2"), *o.prefix("", 32, 32), *o.share("", 32, 32, 8)], LEAVES))
def part_share_weighted(spark, sf):
    grid = grid_of("EV")
    return partition.share_cut(gather(tile_load(events_particles(load(spark, sf, "events"), json_weight()), grid, weight="weight"), grid), 8).frame(spark)


_ELEMENTS = "SELECT ((p_size * 32) // 64) AS ti, ((((round(p_retailprice * 100)::BIGINT - 90000) % 16384) + 16384) % 16384 * 32) // 16384 AS tj, 0 AS p, 1 AS e FROM part"


@query("cost_with_elements", o.join([("p", o.particles("EV")), ("b", f"SELECT {_T} AS ti, {_J} AS tj, 1 AS p, 0 AS e FROM p UNION ALL {_ELEMENTS}"), ("w", "SELECT b::BIGINT AS b FROM (VALUES (0), (1), (10)) t(b)")], "SELECT w.b, ti, tj, sum(p)::BIGINT AS particles, sum(e)::BIGINT AS elements, (sum(p) + w.b * sum(e))::BIGINT AS cost FROM b CROSS JOIN w GROUP BY 1, 2, 3"))
def cost_with_elements(spark, sf):
    grid = grid_of("EV")
    elements = mesh.part_elements(load(spark, sf, "part")).select("elem", (F.col("bx") * (grid.lx // 64)).alias("bx"), (F.col("by") * (grid.ly // 16_384)).alias("by"))
    once = tile_load(particles(spark, sf, "EV"), grid, elements)
    return once.select(F.explode(F.array(*[F.lit(b).cast("long") for b in (0, 1, 10)])).alias("b"), "ti", "tj", "particles", "elements").withColumn("cost", F.col("particles") + F.col("b") * F.col("elements"))


def _tree(first="y", t=10, **how):
    return _loads(tag="") + o.share("", 32, 32, 8, first=first) + _loads(t=t, tag="t")


@query("part_tree_p5", o.join(_loads() + o.share("", 32, 32, 5), "SELECT node, depth, d AS dim, cut, x0, x1, y0, y1, p_first, p AS p_count, false AS is_leaf FROM n"))
def part_tree_p5(spark, sf):
    return partition.share_cut(costs(spark, sf), 5).tree(spark).where("not is_leaf").drop("load")


@query("part_tether_one", o.join(_tree() + o.tether_leaves("t", "", "u", 2), LEAVES + "u"))
def part_tether_one(spark, sf):
    return partition.tethered_cut(partition.share_cut(costs(spark, sf), 8, "y"), costs(spark, sf, t=10)).frame(spark)


@query("part_tether_subtree", o.join(_loads(tag="a") + o.share("a", 32, 32, 8, first="y") + _loads(t=10, tag="t") + o.share("t", 32, 32, 8, first="y", out="u", old="a", frozen=1), LEAVES + "u"))
def part_tether_subtree(spark, sf):
    return partition.tethered_cut(partition.share_cut(costs(spark, sf), 8, "y"), costs(spark, sf, t=10), level=1, frontier="subtree").frame(spark)


@query(
    "part_tether_fallback",
    o.join(
        _tree() + o.tether_leaves("t", "", "u", 2) + o.share("t", 32, 32, 8, first="y", out="w") + [("i", "SELECT max(load) / avg(load) AS imb FROM vu")],
        "SELECT pid, x0, x1, y0, y1, height, load, false AS full FROM vu, i WHERE imb <= 1.25 UNION ALL SELECT pid, x0, x1, y0, y1, height, load, true FROM vw, i WHERE imb > 1.25",
    ),
)
def part_tether_fallback(spark, sf):
    cut, full = partition.tethered_or_full(partition.share_cut(costs(spark, sf), 8, "y"), costs(spark, sf, t=10))
    return cut.frame(spark).withColumn("full", F.lit(full))


def _strips(name, adapter="EV", n=32, rows=(2, 3), first="x", weight=None, cost="count(*)"):
    @query(name, o.join(_loads(adapter, n, 0, "", cost) + o.strips("", n, n, list(rows), first), LEAVES))
    def run(spark, sf):
        return partition.strips(costs(spark, sf, adapter, n, weight=weight), list(rows), first).frame(spark)


_strips("part_strips_2_3")
_strips("part_strips_4x8", n=128, rows=(8, 8, 8, 8))
_strips("part_strips_ydim", adapter="LQ", rows=(4, 4), first="y")
_strips("pages_strips", adapter="PG", rows=(4, 4), weight="weight", cost="sum(weight)")


@query("part_share_3d")
def part_share_3d(spark, sf):
    """Rows only: the proportional cut of three dimensions in turn, for the first three numbers of a vector."""
    import numpy as np

    side, n, parts = 1 << 21, 8, 8
    tile = [F.call_function("div", F.floor((F.get("embedding", F.lit(i)).cast("double") + 1) * 2**20) * n, F.lit(side)).alias(f"t{i}") for i in range(3)]
    rows = load(spark, sf, "embeddings").select(*tile).groupBy("t0", "t1", "t2").count().toArrow()  # a row for each tile at most
    w = np.zeros((n, n, n), np.int64)
    w[tuple(rows.column(f"t{i}").to_numpy() for i in range(3))] = rows.column("count").to_numpy()

    def walk(box, p, first, dim, height):
        if p == 1:
            return [(first, *[e for b in box for e in b], height, int(w[tuple(slice(*b) for b in box)].sum()))]
        for d in (dim, (dim + 1) % 3, (dim + 2) % 3):
            lo, hi = box[d]
            s = np.concatenate([[0], w[tuple(slice(*b) for b in box)].sum(axis=tuple(i for i in range(3) if i != d)).cumsum()])
            if hi - lo > 1:
                q = lo + min(range(1, hi - lo), key=lambda i: (abs(int(s[i]) * p - int(s[-1]) * (p // 2)), i))  # noqa: B023
                sides = [[*box[:d], (lo, q), *box[d + 1 :]], [*box[:d], (q, hi), *box[d + 1 :]]]
                return walk(sides[0], p // 2, first, (d + 1) % 3, height + 1) + walk(sides[1], p - p // 2, first + p // 2, (d + 1) % 3, height + 1)
        raise partition.TooManyProcessors(str(box))

    names = "pid long, x0 long, x1 long, y0 long, y1 long, z0 long, z1 long, height long, load long"
    return spark.createDataFrame(walk([(0, n)] * 3, parts, 0, 0, 0), names)


@query("mesh_graph_cut")
def mesh_graph_cut(spark, sf):
    """Rows only: the off-line baseline's parts of the elements of a hybrid mesh that hold particles; its invariants are tested."""
    from ..operators.lineage import shared

    shared(spark)
    grid = grid_of("EV", 8)
    elements = mesh.hybrid(spark, 8, grid)
    held = mesh.locate_elements(particles(spark, sf, "EV"), elements, grid).select("elem").distinct()
    return mesh.graph_cut(elements.join(held, "elem", "left_semi"), 4, rounds=2)


# diffusion


def _owner_loads(spark, sf) -> DataFrame:
    """Loads of the 16 owners of equal blocks, numbered row by row."""
    cut = partition.even_tiles(grid_of("EV"), 4, 4, costs(spark, sf))
    return spark.createDataFrame([((x.pid % 4) * 4 + x.pid // 4, x.load) for x in cut.leaves], "pid long, load long")


_E44 = _loads() + o.even("0", 32, 32, 4, 4) + o.reload("", "0", "e") + [("w0", "SELECT ((pid % 4) * 4 + pid // 4)::BIGINT AS pid, load::DOUBLE AS load FROM ve")]
_G44 = [
    ("cellg", "SELECT r, c, r * 4 + c AS id, (r + c) % 2 = 1 AS odd FROM range(4) a(r) CROSS JOIN range(4) b(c)"),
    ("g", "SELECT id AS a, id + 1 AS b, CASE WHEN odd THEN 1 ELSE 2 END AS colour FROM cellg WHERE c < 3 UNION ALL SELECT id, id + 4, CASE WHEN odd THEN 3 ELSE 0 END FROM cellg WHERE r < 3"),
    ("gg", "SELECT a, b, colour FROM g UNION ALL SELECT b, a, colour FROM g"),
]


@query("diff_links4x4", o.join(_E44 + _G44, "SELECT g.a::BIGINT AS a, g.b::BIGINT AS b, g.colour::BIGINT AS colour, (p.load - q.load)::BIGINT AS apart FROM g JOIN w0 p ON p.pid = g.a JOIN w0 q ON q.pid = g.b"))
def diff_links4x4(spark, sf):
    """Every link with the difference of its owners' loads."""
    w = _owner_loads(spark, sf)
    a, b = w.select(F.col("pid").alias("a"), F.col("load").alias("wa")), w.select(F.col("pid").alias("b"), F.col("load").alias("wb"))
    return diffusion.colour_grid(spark, 4, 4).join(a, "a").join(b, "b").select("a", "b", "colour", (F.col("wa") - F.col("wb")).alias("apart"))


def _history(steps: int) -> str:
    return " UNION ALL ".join(f"SELECT {t}::BIGINT AS t, pid, round(load, 6) AS load FROM w{t}" for t in range(steps + 1))


@query("diff_colour4x4", o.join(_E44 + _G44 + [(f"w{t}", f"SELECT w.pid, CASE WHEN q.load IS NULL THEN w.load ELSE (w.load + q.load) / 2 END AS load FROM w{t - 1} w LEFT JOIN gg ON gg.a = w.pid AND gg.colour = {t % 4} LEFT JOIN w{t - 1} q ON q.pid = gg.b") for t in range(1, 5)], _history(4)))
def diff_colour4x4(spark, sf):
    return diffusion.exchange(_owner_loads(spark, sf), diffusion.colour_grid(spark, 4, 4), 4).withColumn("load", F.round("load", 6))


def _nation_sql():
    return [
        ("w0", "SELECT n_nationkey::BIGINT AS pid, count(c_custkey)::DOUBLE AS load FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1"),
        ("g", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON b.n_nationkey = a.n_nationkey + 5 UNION ALL SELECT i, i + 1 FROM range(4) t(i)"),
        ("gg", "SELECT a, b FROM g UNION ALL SELECT b, a FROM g"),
    ]


def _diffused(alpha: str, steps: int, extra: str = "0") -> list[tuple[str, str]]:
    return [(f"w{t}", f"SELECT w.pid, w.load + coalesce(f.g, 0) + {extra} AS load FROM w{t - 1} w LEFT JOIN (SELECT gg.a, sum({alpha} * (q.load - m.load)) AS g FROM gg JOIN w{t - 1} q ON q.pid = gg.b JOIN w{t - 1} m ON m.pid = gg.a GROUP BY gg.a) f ON f.a = w.pid") for t in range(1, steps + 1)]


def _nations(spark, sf) -> tuple[DataFrame, DataFrame]:
    n, c = load(spark, sf, "nation"), load(spark, sf, "customer")
    loads = n.join(c, F.col("c_nationkey") == F.col("n_nationkey"), "left").groupBy(F.col("n_nationkey").cast("long").alias("pid")).agg(F.count("c_custkey").alias("load"))
    k = F.col("n_nationkey").cast("long")
    links = n.where("n_nationkey < 20").select(k.alias("a"), (k + 5).alias("b")).union(spark.range(4).select("id", F.col("id") + 1))
    return loads, links


@query("diff_general", o.join(_nation_sql() + _diffused("0.125", 3), _history(3)))
def diff_general(spark, sf):
    loads, links = _nations(spark, sf)
    return diffusion.diffuse(loads, links, 0.125, steps=3).withColumn("load", F.round("load", 6))


@query("diff_uniform", o.join(_nation_sql() + [("deg", "SELECT 1.0::DOUBLE / (max(k) + 1) AS alpha FROM (SELECT a, count(*) AS k FROM gg GROUP BY a)")] + _diffused("(SELECT alpha FROM deg)", 3), _history(3)))
def diff_uniform(spark, sf):
    loads, links = _nations(spark, sf)
    return diffusion.diffuse(loads, links, "uniform", steps=3).withColumn("load", F.round("load", 6))


@query("diff_created", o.join(_nation_sql() + _diffused("0.125", 2, "CASE WHEN w.pid % 5 = 0 THEN 8 ELSE 0 END - CASE WHEN w.pid % 5 = 1 THEN 3 ELSE 0 END"), _history(2)))
def diff_created(spark, sf):
    loads, links = _nations(spark, sf)
    created, consumed = spark.range(0, 25, 5).select(F.col("id").alias("pid"), F.lit(8).alias("load")), spark.range(1, 25, 5).select(F.col("id").alias("pid"), F.lit(3).alias("load"))
    return diffusion.diffuse(loads, links, 0.125, created, consumed, 2).withColumn("load", F.round("load", 6))


@query("diff_link_alpha", o.join(_nation_sql() + _diffused("CASE WHEN abs(gg.a - gg.b) = 5 THEN 0.25 ELSE 0.0625 END", 2), _history(2)))
def diff_link_alpha(spark, sf):
    loads, links = _nations(spark, sf)
    return diffusion.diffuse(loads, links.withColumn("alpha", F.when(F.col("b") - F.col("a") == 5, 0.25).otherwise(0.0625)), "link", steps=2).withColumn("load", F.round("load", 6))


@query("diff_pairwise", o.join([("w0", "SELECT user_id % 4 AS pid, count(*)::DOUBLE AS load FROM events GROUP BY 1"), ("g", "SELECT i AS a, i + 1 AS b FROM range(3) t(i)"), ("gg", "SELECT a, b, a AS low FROM g UNION ALL SELECT b, a, a FROM g")] + [(f"w{t}", f"SELECT w.pid, CASE WHEN q.load IS NULL THEN w.load ELSE (w.load + q.load) / 2 END AS load FROM w{t - 1} w LEFT JOIN gg ON gg.a = w.pid AND gg.low % 2 = {(t + 1) % 2} LEFT JOIN w{t - 1} q ON q.pid = gg.b") for t in range(1, 5)], _history(4)))
def diff_pairwise(spark, sf):
    """A chain of four owners that share the events by user."""
    start = load(spark, sf, "events").groupBy(F.pmod("user_id", F.lit(4)).alias("pid")).agg(F.count("*").alias("load"))
    return diffusion.exchange(start, diffusion.chain(spark, 4), 4).withColumn("load", F.round("load", 6))


def _steps(rows, until, period=None):
    got = _loads() + o.strips("", 32, 32, list(rows), out="z0")
    for t in range(1, until + 1):
        got += o.strip_step("", f"z{t - 1}", f"z{t}", t, 32, 32, bool(period and t % period == 0))
    return got


def _strip_steps(name, rows, until, period=None, start="strips"):
    @query(name, o.join(_steps(rows, until, period), f"{LEAVES}z{until}"))
    def run(spark, sf):
        loads = costs(spark, sf)
        cut = partition.strips(loads, list(rows))
        for t in range(1, until + 1):
            cut = diffusion.strip_exchange(cut, loads, t, period)
        return cut.frame(spark)


_strip_steps("diff_strip_t1", (4, 4), 1)
_strip_steps("diff_strip_t2", (4, 4), 2)
_strip_steps("diff_strip_2_3", (2, 3), 2)
_strip_steps("diff_strip_columns", (3, 5), 4, 4)


def _even_steps(until):
    """Strips that begin as equal blocks: their borders in the builders' form."""
    got = _loads() + [
        ("kz0", "SELECT c::BIGINT AS c, (16 * c)::BIGINT AS a, (16 * c + 16)::BIGINT AS b, 4::BIGINT AS size, (4 * c)::BIGINT AS base FROM range(2) t(c)"),
        ("rz0", "SELECT c::BIGINT AS c, k::BIGINT AS k, (8 * k)::BIGINT AS q FROM range(2) a(c) CROSS JOIN range(5) b(k)"),
        *o.strip_leaves("", "z0"),
    ]
    for t in range(1, until + 1):
        got += o.strip_step("", f"z{t - 1}", f"z{t}", t, 32, 32)
    return got


@query("diff_even_history", o.join(_even_steps(5), " UNION ALL ".join(f"SELECT {t}::BIGINT AS t, pid, load FROM vz{t}" for t in range(6))))
def diff_even_history(spark, sf):
    loads = costs(spark, sf)
    cut = partition.even_tiles(grid_of("EV"), 2, 4, loads)
    rows = [(0, x.pid, x.load) for x in cut.leaves]
    for t in range(1, 6):
        cut = diffusion.strip_exchange(cut, loads, t)
        rows += [(t, x.pid, x.load) for x in cut.leaves]
    return spark.createDataFrame(rows, "t long, pid long, load long")


def _cv():
    got = _loads("CV", 32, 0, "", "sum(weight)") + o.strips("", 32, 32, [4, 4], out="z0")
    for t in (1, 2, 3):
        got += o.strip_step("", f"z{t - 1}", f"z{t}", t, 32, 32)
    return got


@query("conv_exchange", o.join(_cv(), LEAVES + "z3"))
def conv_exchange(spark, sf):
    loads = costs(spark, sf, "CV", weight="weight")
    cut = partition.strips(loads, [4, 4])
    for t in (1, 2, 3):
        cut = diffusion.strip_exchange(cut, loads, t)
    return cut.frame(spark)


# placement


def _cut0(spark, sf, parts=8, first="x"):
    return partition.share_cut(costs(spark, sf), parts, first)


_BASE = _loads() + o.share("", 32, 32, 8)
_OWN = lambda v, a="v": o.owner_join("p", v, "EV", 32, 32, a)


@query("place_fixed_static", o.join(_BASE + [("q", o.particles("EV", 50))], f"SELECT p.pid_key, q.x, q.y, v.pid AS owner FROM p {_OWN('')} JOIN q ON q.pid_key = p.pid_key"))
def place_fixed_static(spark, sf):
    grid = grid_of("EV")
    return pic.push(placement.fixed_owner(particles(spark, sf, "EV"), _cut0(spark, sf), grid), grid, 50).select("pid_key", "x", "y", "owner")


@query("place_fixed_dynamic", o.join(_loads(t=10, tag="t") + o.share("t", 32, 32, 8) + [("p", o.particles("EV", 10)), ("q", o.particles("EV", 50))], f"SELECT p.pid_key, q.x, q.y, v.pid AS owner FROM p {_OWN('t')} JOIN q ON q.pid_key = p.pid_key"))
def place_fixed_dynamic(spark, sf):
    """Rebalanced at step 10, where particles go to the owners of their places; they keep these until step 50."""
    grid = grid_of("EV")
    cut = partition.share_cut(costs(spark, sf, t=10), 8)
    return pic.push(placement.fixed_owner(at(spark, sf, t=10), cut, grid), grid, 40).select("pid_key", "x", "y", "owner")


@query("place_site_static", o.join(_BASE + [("pp", o.particles("EV", 50))], "SELECT p.pid_key, p.x, p.y, v.pid AS owner FROM pp p " + _OWN("")))
def place_site_static(spark, sf):
    return placement.site_owner(at(spark, sf, t=50), _cut0(spark, sf), grid_of("EV")).select("pid_key", "x", "y", "owner")


@query("place_site_dynamic", o.join(_loads(t=50, tag="t") + o.share("t", 32, 32, 8), f"SELECT p.pid_key, p.x, p.y, v.pid AS owner FROM pt p {_OWN('t')}"))
def place_site_dynamic(spark, sf):
    cut = partition.share_cut(costs(spark, sf, t=50), 8)
    return placement.site_owner(at(spark, sf, t=50), cut, grid_of("EV")).select("pid_key", "x", "y", "owner")


def _both(spark, sf, t=10):
    """Particles at step t with their owner at step 0 and now, under the first cut."""
    grid, cut = grid_of("EV"), _cut0(spark, sf)
    return placement.site_owner(pic.push(placement.site_owner(particles(spark, sf, "EV"), cut, grid, "owner0"), grid, t), cut, grid), cut, grid


_MOVED = _BASE + [("pp", o.particles("EV", 10)), ("o0", f"SELECT p.pid_key, v.pid AS owner0 FROM p {_OWN('')}"), ("o1", f"SELECT p.pid_key, p.x, p.y, v.pid AS owner FROM pp p {_OWN('')}")]


@query("place_migrations", o.join(_MOVED, "SELECT owner0 AS src, owner AS dst, count(*) AS n FROM o0 JOIN o1 USING (pid_key) WHERE owner0 <> owner GROUP BY 1, 2"))
def place_migrations(spark, sf):
    return placement.migrations(_both(spark, sf)[0])


@query("place_leavers", o.join(_MOVED, "SELECT pid_key, owner0 AS owner FROM o0 JOIN o1 USING (pid_key) WHERE owner0 <> owner"))
def place_leavers(spark, sf):
    df, cut, grid = _both(spark, sf)
    return placement.leavers(df.drop("owner").withColumnRenamed("owner0", "owner"), cut.frame(spark), grid).select("pid_key", "owner")


@query("place_move", o.join(_MOVED, "SELECT pid_key, owner0, owner FROM o0 JOIN o1 USING (pid_key)"))
def place_move(spark, sf):
    return placement.move(_both(spark, sf)[0], 8).select("pid_key", "owner0", "owner")


@query("place_hash_baseline", o.join([("p", o.particles("EV"))], f"SELECT (pid_key % 8)::BIGINT AS pid, count(*) AS load, count(DISTINCT {_T} * 32 + {_J}) AS tiles_seen FROM p GROUP BY 1"))
def place_hash_baseline(spark, sf):
    df, grid = placement.hash_owner(particles(spark, sf, "EV"), 8), grid_of("EV")
    return metrics.owner_loads(df, 8).join(metrics.footprint(df, grid), "pid")


@query("place_elements", o.join(_BASE + mesh_sql("hybrid", 16, 2592000000000, 65536), "SELECT e.elem, v.pid AS owner FROM e JOIN v ON (bx * 32) // 2592000000000 >= x0 AND (bx * 32) // 2592000000000 < x1 AND (cy * 32) // 65536 >= y0 AND (cy * 32) // 65536 < y1"))
def place_elements(spark, sf):
    grid = grid_of("EV")
    return placement.own_elements(mesh.hybrid(spark, 16, grid), _cut0(spark, sf), grid).select("elem", "owner")


# runs

_TIMES = (0, 10, 50, 100)


def _dyn_rows(spark, rows):
    return spark.createDataFrame(rows, "t long, max_load long, imbalance double")


def _dyn_sql(make) -> str:
    ctes, selects = make
    return o.join(ctes, " UNION ALL ".join(f"SELECT {t}::BIGINT AS t, max(load)::BIGINT AS max_load, round(max(load) / avg(load), 6) AS imbalance FROM v{v}" for t, v in selects))


def _static(first_ctes):
    ctes, picks = _loads() + first_ctes, []
    for t in _TIMES:
        ctes += _loads(t=t, tag=f"t{t}") + o.reload(f"t{t}", "", f"s{t}")
        picks.append((t, f"s{t}"))
    return ctes, picks


def _series(spark, sf, make):
    rows = []
    for t in _TIMES:
        loads = costs(spark, sf, t=t)
        got = make(t, loads).reloaded(loads).loads()
        rows.append((t, max(got), round(partition.imbalance(got), 6)))
    return _dyn_rows(spark, rows)


@query("dyn_static_share", _dyn_sql(_static(o.share("", 32, 32, 8, first="y"))))
def dyn_static_share(spark, sf):
    cut = _cut0(spark, sf, first="y")
    return _series(spark, sf, lambda t, loads: cut)


@query("dyn_static_strips", _dyn_sql(_static(o.strips("", 32, 32, [4, 4]))))
def dyn_static_strips(spark, sf):
    cut = partition.strips(costs(spark, sf), [4, 4])
    return _series(spark, sf, lambda t, loads: cut)


@query("dyn_static_even", _dyn_sql(_static(o.even("", 32, 32, 4, 2))))
def dyn_static_even(spark, sf):
    cut = partition.even_tiles(grid_of("EV"), 4, 2)
    return _series(spark, sf, lambda t, loads: cut)


def _owner_map(v: str) -> str:
    return f"SELECT i AS ti, j AS tj, pid FROM v{v}, LATERAL (SELECT unnest(range(x0, x1)) AS i) a, LATERAL (SELECT unnest(range(y0, y1)) AS j) b"


def _versus() -> str:
    ctes = _loads() + o.share("", 32, 32, 8, first="y") + [("m", _owner_map(""))]
    picks = []
    for t in (10, 50, 100):
        ctes += _loads(t=t, tag=f"t{t}") + o.share(f"t{t}", 32, 32, 8, first="y", out=f"f{t}") + o.tether_leaves(f"t{t}", "", f"h{t}", 2)
        for kind, v in (("full", f"f{t}"), ("tethered", f"h{t}")):
            ctes.append((f"m{v}", _owner_map(v)))
            picks.append(f"SELECT '{kind}' AS kind, {t}::BIGINT AS t, (SELECT round(max(load) / avg(load), 6) FROM v{v}) AS imbalance, count(*) AS tiles_moved, coalesce(sum(l.cost), 0)::BIGINT AS particles_moved FROM m JOIN m{v} q USING (ti, tj) LEFT JOIN lt{t} l USING (ti, tj) WHERE m.pid <> q.pid")
    return o.join(ctes, " UNION ALL ".join(picks))


@query("dyn_share_vs_tether", _versus())
def dyn_share_vs_tether(spark, sf):
    """What limited moves of a cut save in migration, and what they cost in balance."""
    old, rows = _cut0(spark, sf, first="y"), []
    for t in (10, 50, 100):
        loads = costs(spark, sf, t=t)
        for kind, cut in (("full", partition.share_cut(loads, 8, "y")), ("tethered", partition.tethered_cut(old, loads))):
            moved = old.owners() != cut.owners()
            rows.append((kind, t, round(partition.imbalance(cut.loads()), 6), int(moved.sum()), int(loads.cost[moved].sum())))
    return spark.createDataFrame(rows, "kind string, t long, imbalance double, tiles_moved long, particles_moved long")


# measures


@query("met_imbalance", o.join(_BASE, "SELECT max(load)::BIGINT AS max_load, round(avg(load), 6) AS mean_load, round(max(load) / avg(load), 6) AS imbalance FROM v"))
def met_imbalance(spark, sf):
    df = placement.site_owner(particles(spark, sf, "EV"), _cut0(spark, sf), grid_of("EV"))
    return metrics.imbalance(metrics.owner_loads(df, 8))


@query("met_migration", o.join(_BASE + o.even("e", 32, 32, 4, 2) + [("m", _owner_map("")), ("me", _owner_map("e"))], "SELECT count(*) AS tiles_moved, coalesce(sum(l.cost), 0)::BIGINT AS particles_moved FROM m JOIN me q USING (ti, tj) LEFT JOIN l USING (ti, tj) WHERE m.pid <> q.pid"))
def met_migration(spark, sf):
    grid = grid_of("EV")
    loads = tile_load(particles(spark, sf, "EV"), grid)
    return metrics.migration(partition.even_owner(spark, grid, 4, 2), partition.expand(_cut0(spark, sf).frame(spark)), loads)


@query("met_perimeter", o.join(_BASE, "SELECT sum(2 * (x1 - x0 + y1 - y0))::BIGINT AS perimeter_sum, max(2 * (x1 - x0 + y1 - y0))::BIGINT AS perimeter_max FROM v"))
def met_perimeter(spark, sf):
    return metrics.perimeter(_cut0(spark, sf).frame(spark))


_RATIO = "greatest(x1 - x0, y1 - y0)::DOUBLE / least(x1 - x0, y1 - y0)"


@query("met_aspect", o.join(_BASE, f"SELECT round(max({_RATIO}), 6) AS max_aspect, round(avg({_RATIO}), 6) AS mean_aspect FROM v"))
def met_aspect(spark, sf):
    return metrics.aspect(_cut0(spark, sf).frame(spark))


@query("met_halo", o.join(_BASE + [("m", _owner_map(""))], "SELECT count(*) AS pairs, count(*) FILTER (WHERE m.pid <> q.pid) AS cut FROM m JOIN (VALUES (1, 0), (0, 1)) d(a, b) ON true JOIN m q ON q.ti = (m.ti + a) % 32 AND q.tj = (m.tj + b) % 32"))
def met_halo(spark, sf):
    return metrics.cut_edges(partition.expand(_cut0(spark, sf).frame(spark)), grid_of("EV"))


@query("met_footprint", o.join(_BASE + [("pp", o.particles("EV", 50))], f"SELECT v.pid, count(DISTINCT ((q.x * 32) // 2592000000000) * 32 + (q.y * 32) // 65536) AS tiles_seen FROM p {_OWN('')} JOIN pp q ON q.pid_key = p.pid_key GROUP BY 1"))
def met_footprint(spark, sf):
    """Tiles that the particles of fixed owners see after fifty steps."""
    grid = grid_of("EV")
    return metrics.footprint(pic.push(placement.fixed_owner(particles(spark, sf, "EV"), _cut0(spark, sf), grid), grid, 50), grid)


@query("met_conservation", o.join([("p", o.particles("EV", 50))], "SELECT count(*) AS particles, sum(weight)::BIGINT AS charge FROM p"))
def met_conservation(spark, sf):
    return metrics.conservation(at(spark, sf, t=50))


@query("met_convergence", o.join(_nation_sql() + _diffused("0.125", 3), "SELECT t, round(max(load) - min(load), 4) AS spread, round(sum(load), 4) AS total FROM (" + _history(3) + ") GROUP BY t"))
def met_convergence(spark, sf):
    loads, links = _nations(spark, sf)
    return diffusion.convergence(diffusion.diffuse(loads, links, 0.125, steps=3)).select("t", F.round("spread", 4).alias("spread"), F.round("total", 4).alias("total"))


@query("met_model_cost", o.join(_MOVED + [("seen", f"SELECT owner AS pid, count(DISTINCT {_T} * 32 + {_J}) AS s FROM o1 GROUP BY 1"), ("held", "SELECT owner AS pid, count(*) AS h FROM o1 GROUP BY 1"), ("gone", "SELECT owner0 AS pid, count(*) AS g FROM o0 JOIN o1 USING (pid_key) WHERE owner0 <> owner GROUP BY 1")], "SELECT max(coalesce(h, 0) + 4 * coalesce(s, 0) + 8 * coalesce(g, 0) + 16 * 2 * (x1 - x0 + y1 - y0))::BIGINT AS step_cost FROM v LEFT JOIN held USING (pid) LEFT JOIN seen USING (pid) LEFT JOIN gone USING (pid)"))
def met_model_cost(spark, sf):
    df, cut, grid = _both(spark, sf)
    left = placement.migrations(df).groupBy(F.col("src").alias("pid")).agg(F.sum("n").alias("n"))
    borders = cut.frame(spark).select("pid", (2 * (F.col("x1") - F.col("x0") + F.col("y1") - F.col("y0"))).alias("length"))
    return metrics.model_cost(metrics.owner_loads(df, 8), metrics.footprint(df, grid), left, borders)


@query("met_mesh_counts", o.join([("h", f"SELECT DISTINCT ((x * 8) // 2592000000000 * 8 + (y * 8) // 65536) * 2 AS base FROM ({o.particles('EV')})")] + [(k, v) if k != "q" else (k, v + " WHERE u.elem - u.elem % 2 IN (SELECT base FROM h)") for k, v in mesh_sql("hybrid", 8, 2592000000000, 65536)] + [("n", "SELECT elem, count(*) AS k FROM q GROUP BY elem"), ("s", "SELECT a.elem, least((a.x, a.y), (b.x, b.y)) AS u, greatest((a.x, a.y), (b.x, b.y)) AS v FROM q a JOIN n USING (elem) JOIN q b ON b.elem = a.elem AND b.c = (a.c + 1) % n.k")], "SELECT (SELECT count(*) FROM e) AS elements, (SELECT count(DISTINCT (u, v)) FROM s) AS edges, (SELECT count(DISTINCT (x, y)) FROM q) AS vertices"))
def met_mesh_counts(spark, sf):
    """Counts of the elements whose cells hold particles."""
    grid = grid_of("EV")
    held = mesh.locate_quads(particles(spark, sf, "EV"), 8, grid).select(F.col("elem").alias("base")).distinct()
    elements = mesh.hybrid(spark, 8, grid)
    return mesh.counts(elements.join(held, F.col("elem") - F.pmod("elem", F.lit(2)) == F.col("base"), "left_semi"))


@query("met_ratio", o.join(_static(o.share("", 32, 32, 8, first="y"))[0], " UNION ALL ".join(f"SELECT {t}::BIGINT AS t, round((SELECT max(load) FROM vs{t}) / (SELECT max(load) FROM vs0), 6) AS ratio" for t in _TIMES)))
def met_ratio(spark, sf):
    return metrics.ratio(dyn_static_share(spark, sf), "t", 0, "max_load").select("t", "ratio")
