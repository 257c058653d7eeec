"""The experiments: mesh sizes, placement by partitioning, steps, mesh kinds, two streams, illustrations."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import mesh, partition, pic
from ..operators.cost import LoadMap, gather, tile_load
from ..operators.grid import Grid, locate
from ..oracle import text as o
from ..sources.tables import DOMAINS, grid_of, particles, two_stream
from .methods import _loads, _owner_map, costs, gradient_sql, mesh_sql
from .policy import Every, Never, Threshold
from .registry import query
from .simulate import Run, run

SIZES = (16, 32, 64, 128)


def coarser(loads: LoadMap, by: int) -> LoadMap:
    """Costs of tiles by times as wide and high: exact, as tiles of a coarser grid are unions of finer ones."""
    return LoadMap(loads.cost.reshape(loads.n // by, by, loads.m // by, by).sum((1, 3)))


# mesh sizes: regular and unstructured meshes, strips of 4 columns by 8 rows, cost of particles and elements


def _mesh_sweep_sql(kind: str) -> str:
    ctes, picks = [], []
    for k in SIZES:
        ctes += [(f"{name}{k}", body) for name, body in _renamed(mesh_sql(kind, k, *DOMAINS["EV"]), str(k))]
        lx, ly = DOMAINS["EV"]
        ctes += [(f"pw{k}", o.particles("EV")), (f"l{k}", f"SELECT ti, tj, count(*) AS cost FROM (SELECT (x * {k}) // {lx} AS ti, (y * {k}) // {ly} AS tj FROM pw{k} UNION ALL SELECT (bx * {k}) // {lx}, (cy * {k}) // {ly} FROM e{k}) GROUP BY 1, 2")]
        ctes += o.prefix(str(k), k, k) + o.strips(str(k), k, k, [8] * 4, out=f"s{k}")
        picks.append(f"SELECT {k}::BIGINT AS k, (SELECT count(*) FROM e{k}) AS elements, max(load)::BIGINT AS max_load, round(max(load) / avg(load), 6) AS imbalance, sum(2 * (x1 - x0 + y1 - y0))::BIGINT AS perimeter FROM vs{k}")
    return o.join(ctes, " UNION ALL ".join(picks))


def _renamed(ctes, tag: str):
    """A mesh's expressions under names of their own: vx, cell, q and e become vx<tag> and so on."""
    out = []
    for name, body in ctes:
        for was in ("vx", "cell", "q"):
            body = body.replace(f"JOIN {was} ", f"JOIN {was}{tag} ").replace(f"FROM {was} ", f"FROM {was}{tag} ")
        out.append((name, body))
    return out


for _kind in ("quads", "triangles"):

    @query(f"w1_mesh_sweep_{'quads' if _kind == 'quads' else 'tris'}", _mesh_sweep_sql(_kind))
    def w1_mesh_sweep(spark, sf, kind=_kind):
        fine = costs(spark, sf, n=SIZES[-1])
        rows = []
        for k in SIZES:
            grid = grid_of("EV", k)
            made = getattr(mesh, kind)(spark, k, grid)
            of_elements = gather(tile_load(None, grid, made, b=1), grid)
            cut = partition.strips(LoadMap(coarser(fine, SIZES[-1] // k).cost + of_elements.cost), [8] * 4)
            rows.append((k, of_elements.total, max(cut.loads()), round(partition.imbalance(cut.loads()), 6), sum(2 * (x.x1 - x.x0 + x.y1 - x.y0) for x in cut.leaves)))
        return spark.createDataFrame(rows, "k long, elements long, max_load long, imbalance double, perimeter long")


# placement by partitioning

_TIMES = (0, 10, 50)


def _matrix_cuts_sql():
    """Cuts of every policy and time, as names of v."""
    ctes = _loads(tag="a0") + o.share("a0", 32, 32, 8, first="y", out="share0") + o.strips("a0", 32, 32, [4, 4], out="strips0") + o.even("even0", 32, 32, 4, 2)
    names = {}
    for t in _TIMES:
        tag = f"a{t}"
        if t:
            ctes += _loads(t=t, tag=tag) + o.share(tag, 32, 32, 8, first="y", out=f"share{t}") + o.strips(tag, 32, 32, [4, 4], out=f"strips{t}") + o.tether_leaves(tag, "share0", f"tether{t}", 2)
        names[t] = {"static_share": "share0", "static_strips": "strips0", "static_even": "even0", "share": f"share{t}", "tethered": f"tether{t}" if t else "share0", "strips": f"strips{t}"}
    return ctes, names


def _matrix_sql() -> str:
    ctes, names = _matrix_cuts_sql()
    for v in {v for x in names.values() for v in x.values()}:
        ctes.append((f"m{v}", _owner_map(v)))
    tile = lambda a: f"(({a}.x * 32) // 2592000000000) AS ti, (({a}.y * 32) // 65536) AS tj"
    for t in _TIMES:
        ctes.append((f"z{t}", f"SELECT pid_key, {tile(f'pa{t}')} FROM pa{t}"))
    picks = []
    for t in _TIMES:
        for policy, v in names[t].items():
            first = names[0][policy]
            for placed in ("site", "fixed"):
                # fixed owners are renewed only where the mapping is made anew
                own = f"m{v} w ON w.ti = z.ti AND w.tj = z.tj" if placed == "site" or not policy.startswith("static") else f"m{first} w ON w.ti = z0.ti AND w.tj = z0.tj"
                body = f"SELECT w.pid, z.ti * 32 + z.tj AS tile, (w.pid <> b.pid)::INT AS moved FROM z{t} z JOIN z0 USING (pid_key) JOIN m{first} b ON b.ti = z0.ti AND b.tj = z0.tj JOIN {own}"
                picks.append(f"SELECT '{policy}' AS policy, '{placed}' AS placement, {t}::BIGINT AS t, max(n)::BIGINT AS max_load, round(max(n) * 8 / sum(n), 6) AS imbalance, max(f)::BIGINT AS footprint, sum(k)::BIGINT AS moved FROM (SELECT pid, count(*) AS n, count(DISTINCT tile) AS f, sum(moved) AS k FROM ({body}) GROUP BY pid)")
    return o.join(ctes, " UNION ALL ".join(picks))


def policies(spark, sf):
    """Cut of each policy at each time, and the first ones."""
    first = costs(spark, sf)
    share0, strips0, even0 = partition.share_cut(first, 8, "y"), partition.strips(first, [4, 4]), partition.even_tiles(grid_of("EV"), 4, 2, first)
    out = {}
    for t in _TIMES:
        loads = costs(spark, sf, t=t) if t else first
        out[t] = {"static_share": share0, "static_strips": strips0, "static_even": even0, "share": partition.share_cut(loads, 8, "y"), "tethered": partition.tethered_cut(share0, loads), "strips": partition.strips(loads, [4, 4])}
    return out


@query("w2_matrix", _matrix_sql())
def w2_matrix(spark, sf):
    """Every policy under either ownership: one pass over the particles per time, all owners on the row."""
    grid, cuts = grid_of("EV"), policies(spark, sf)
    rows = None
    for t in _TIMES:
        df = locate(particles(spark, sf, "EV"), grid).withColumnsRenamed({"ti": "i0", "tj": "j0"})
        df = locate(pic.push(df, grid, t), grid)
        structs = []
        for policy, cut in cuts[t].items():
            before, now = cuts[0][policy].owner("i0", "j0"), cut.owner()
            for placed in ("site", "fixed"):
                pid = now if placed == "site" or not policy.startswith("static") else before
                structs.append(F.struct(F.lit(policy).alias("policy"), F.lit(placed).alias("placement"), pid.alias("pid"), (pid != before).cast("long").alias("moved")))
        every = df.select("ti", "tj", F.explode(F.array(*structs)).alias("s")).select("ti", "tj", "s.*")
        per = every.groupBy("policy", "placement", "pid").agg(F.count("*").alias("n"), F.count_distinct(F.col("ti") * 32 + F.col("tj")).alias("f"), F.sum("moved").alias("k"))
        one = per.groupBy("policy", "placement").agg(F.max("n").alias("max_load"), F.round(F.max("n") * 8 / F.sum("n"), 6).alias("imbalance"), F.max("f").alias("footprint"), F.sum("k").alias("moved"))
        one = one.select("policy", "placement", F.lit(t).cast("long").alias("t"), "max_load", "imbalance", "footprint", "moved")
        rows = one if rows is None else rows.union(one)
    return rows


# steps

_STEPS = 5


def _per_step_sql() -> str:
    ctes = _loads() + o.share("", 32, 32, 8) + [("m", _owner_map(""))]
    for t in range(_STEPS + 1):
        ctes += [(f"q{t}", o.particles("EV", t)), (f"z{t}", f"SELECT pid_key, (x * 32) // 2592000000000 AS ti, (y * 32) // 65536 AS tj FROM q{t}"), (f"o{t}", f"SELECT z.pid_key, z.ti, z.tj, m.pid FROM z{t} z JOIN m USING (ti, tj)")]
    picks = []
    for t in range(1, _STEPS + 1):
        picks.append(f"SELECT 'site' AS placement, {t}::BIGINT AS t, max(n)::BIGINT AS max_load, max(f)::BIGINT AS elements_seen_max, (SELECT count(*) FROM o{t} a JOIN o{t - 1} b USING (pid_key) WHERE a.pid <> b.pid) AS particles_moved FROM (SELECT pid, count(*) AS n, count(DISTINCT ti * 32 + tj) AS f FROM o{t} GROUP BY 1)")
        picks.append(f"SELECT 'fixed' AS placement, {t}::BIGINT AS t, max(n)::BIGINT AS max_load, max(f)::BIGINT AS elements_seen_max, 0 AS particles_moved FROM (SELECT o0.pid, count(*) AS n, count(DISTINCT z.ti * 32 + z.tj) AS f FROM o0 JOIN z{t} z USING (pid_key) GROUP BY 1)")
    return o.join(ctes, " UNION ALL ".join(picks))


@query("w3_per_step", _per_step_sql())
def w3_per_step(spark, sf):
    out = None
    for placed in ("site", "fixed"):
        _, history = run(particles(spark, sf, "EV"), Run(grid_of("EV"), 8, _STEPS, placed, Never()))
        one = history.where("t > 0").select(F.lit(placed).alias("placement"), "t", "max_load", "elements_seen_max", "particles_moved")
        out = one if out is None else out.union(one)
    return out


def _run_sql(k: int, steps: int) -> str:
    """A run under site ownership whose cut is made anew at every k-th step."""
    ctes, last = [], 0
    for t in range(0, steps + 1, k):
        ctes += _loads(t=t, tag=f"b{t}") + o.share(f"b{t}", 32, 32, 8) + [(f"mb{t}", _owner_map(f"b{t}"))]
    picks = []
    for t in range(steps + 1):
        last = t // k * k
        ctes += [(f"q{t}", o.particles("EV", t)), (f"o{t}", f"SELECT z.pid_key, z.ti, z.tj, m.pid FROM (SELECT pid_key, (x * 32) // 2592000000000 AS ti, (y * 32) // 65536 AS tj FROM q{t}) z JOIN mb{last} m USING (ti, tj)")]
        if t:
            picks.append(f"SELECT {t}::BIGINT AS t, {t % k == 0} AS rebalanced, {1 + t // k}::BIGINT AS syncs, max(n)::BIGINT AS max_load, round(max(n) * 8 / sum(n), 6)::DOUBLE AS imbalance, max(f)::BIGINT AS elements_seen_max, (SELECT count(*) FROM o{t} a JOIN o{t - 1} b USING (pid_key) WHERE a.pid <> b.pid) AS particles_moved FROM (SELECT pid, count(*) AS n, count(DISTINCT ti * 32 + tj) AS f FROM o{t} GROUP BY 1)")
    return o.join(ctes, " UNION ALL ".join(picks))


def _run(spark, sf, policy, steps: int):
    _, history = run(particles(spark, sf, "EV"), Run(grid_of("EV"), 8, steps, "site", policy))
    return history.where("t > 0").select("t", "rebalanced", "syncs", "max_load", F.round("imbalance", 6).alias("imbalance"), "elements_seen_max", "particles_moved")


@query("run_every_2", _run_sql(2, 4))
def run_every_2(spark, sf):
    """A whole run with a cut from scratch at every second step."""
    return _run(spark, sf, Every(2), 4)


@query("run_threshold", _run_sql(1, 3))
def run_threshold(spark, sf):
    """A whole run with a cut from scratch whenever the greatest load is above the mean, which it is at each step."""
    return _run(spark, sf, Threshold(1.0), 3)


# mesh kinds


def _kinds_sql(n: int = 128, parts: int = 32, t: int = 10) -> str:
    lx, ly = DOMAINS["EV"]
    ctes, picks = [("w0", o.particles("EV")), (f"w{t}", o.particles("EV", t))], []
    for kind in ("quads", "triangles", "hybrid"):
        g = kind[0]
        ctes += [(f"{name}{g}", body) for name, body in _renamed(mesh_sql(kind, n, lx, ly), g)]
        ctes.append((f"y{g}", f"SELECT (bx * {n}) // {lx} AS ti, (cy * {n}) // {ly} AS tj FROM e{g}"))
        for when in (0, t):
            tag = f"{g}{when}"
            ctes += [(f"l{tag}", f"SELECT ti, tj, count(*) AS cost FROM (SELECT (x * {n}) // {lx} AS ti, (y * {n}) // {ly} AS tj FROM w{when} UNION ALL SELECT * FROM y{g}) GROUP BY 1, 2"), *o.prefix(tag, n, n)]
        ctes += o.share(f"{g}0", n, n, parts, out=f"sh{g}") + o.reload(f"{g}{t}", f"sh{g}", f"st{g}") + o.tether_leaves(f"{g}{t}", f"sh{g}", f"te{g}", 4) + o.strips(f"{g}{t}", n, n, [8] * 4, out=f"sp{g}")
        for policy, v in (("static_share", f"st{g}"), ("tethered", f"te{g}"), ("strips", f"sp{g}")):
            picks.append(f"SELECT '{kind}' AS mesh, '{policy}' AS policy, (SELECT count(*) FROM e{g}) AS elements, max(load)::BIGINT AS max_load, round(max(load) / avg(load), 6) AS imbalance FROM v{v}")
    return o.join(ctes, " UNION ALL ".join(picks))


@query("w4_mesh_kinds", _kinds_sql())
def w4_mesh_kinds(spark, sf):
    grid = grid_of("EV", 128)
    parts = {t: costs(spark, sf, n=128, t=t) for t in (0, 10)}
    rows = []
    for kind in ("quads", "triangles", "hybrid"):
        of_elements = gather(tile_load(None, grid, getattr(mesh, kind)(spark, 128, grid), b=1), grid)
        first, now = (LoadMap(parts[t].cost + of_elements.cost) for t in (0, 10))
        cut = partition.share_cut(first, 32)
        for policy, c in (("static_share", cut.reloaded(now)), ("tethered", partition.tethered_cut(cut, now)), ("strips", partition.strips(now, [8] * 4))):
            rows.append((kind, policy, of_elements.total, max(c.loads()), round(partition.imbalance(c.loads()), 6)))
    return spark.createDataFrame(rows, "mesh string, policy string, elements long, max_load long, imbalance double")


# two streams

_N, _L = 20_000, 1 << 20


def _two_stream_sql(steps: int = 3, n: int = 32) -> str:
    even = f"floor(i * ({_L / _N}::DOUBLE))::BIGINT"
    start = f"SELECT i::BIGINT AS pid_key, (({even} + round({_L / 1000}::DOUBLE * cos(2 * 3.141592653589793::DOUBLE / {_L} * {even}))::BIGINT) % {_L} + {_L}) % {_L} AS x, (i * 648056) % {_L} AS y, CASE WHEN i % 2 = 0 THEN 4096 ELSE -4096 END AS vx, 0 AS vy, 1 AS weight, i % 2 AS species FROM range({_N}) t(i)"
    got = [("k0", start)]
    for s in range(steps):
        d = [(a, b.replace("2592000000000", str(_L)).replace("65536", str(_L))) for a, b in gradient_sql(f"k{s}", str(s), n)]
        got += d
        got.append((f"k{s + 1}", f"SELECT pid_key, (({o.mod('x + vx', _L)}))::BIGINT AS x, ({o.mod('y + vy', _L)})::BIGINT AS y, vx, vy, weight, species FROM (SELECT pid_key, x, y, vx + CASE WHEN species = 0 THEN 1 ELSE -1 END * coalesce(fx, 0) AS vx, vy + CASE WHEN species = 0 THEN 1 ELSE -1 END * coalesce(fy, 0) AS vy, weight, species FROM k{s} p LEFT JOIN f{s} f ON f.ti = (x * {n}) // {_L} AND f.tj = (y * {n}) // {_L})"))
    return o.join(got, f"SELECT pid_key, x, y, vx::BIGINT AS vx, vy::BIGINT AS vy FROM k{steps}")


@query("w5_two_stream", _two_stream_sql())
def w5_two_stream(spark, sf):
    grid, df = Grid(32, 32, _L, _L), two_stream(spark, _N, _L, _L)
    for _ in range(3):
        df = pic.step(df, grid)
    return df.select("pid_key", "x", "y", "vx", "vy")


@query("w5_two_stream_energy")
def w5_two_stream_energy(spark, sf):
    """Rows only: energy of the field's gradient by step, whose growth the tests bound."""
    from ..operators.fields import tile_gradient

    grid, df, rows = Grid(64, 1, _L, _L), two_stream(spark, _N, _L, _L), []
    from ..operators.lineage import shared

    shared(spark)
    for t in range(4):
        field = tile_gradient(pic.deposit(df, grid), grid)
        rows.append(field.agg(F.lit(t).cast("long").alias("t"), F.sum(F.col("fx").cast("double") ** 2).alias("energy")))
        df = pic.push(pic.interpolate(df, field, grid), grid, force=True).checkpoint()
    out = rows[0]
    for more in rows[1:]:
        out = out.union(more)
    return out


# illustrations


@query("part_compare_owner", o.join(_loads() + o.share("", 32, 32, 8, out="a") + o.strips("", 32, 32, [4, 4], out="b") + [("ma", _owner_map("a")), ("mb", _owner_map("b"))], "SELECT ti, tj, ma.pid AS share, mb.pid AS strips FROM ma JOIN mb USING (ti, tj)"))
def part_compare_owner(spark, sf):
    loads = costs(spark, sf)
    a, b = (partition.expand(c.frame(spark)) for c in (partition.share_cut(loads, 8), partition.strips(loads, [4, 4])))
    return a.withColumnRenamed("pid", "share").join(b.withColumnRenamed("pid", "strips"), ["ti", "tj"])


def _skewed_sql() -> str:
    ctes, picks = _loads("LQ") + o.share("", 32, 32, 8), []
    for t in (0, 10):
        ctes += _loads("LQ", t=t, tag=f"t{t}") + o.reload(f"t{t}", "", f"s{t}") + o.share(f"t{t}", 32, 32, 8, out=f"f{t}") + o.strips(f"t{t}", 32, 32, [4, 4], out=f"p{t}")
        picks += [f"SELECT '{k}' AS policy, {t}::BIGINT AS t, max(load)::BIGINT AS max_load, round(max(load) / avg(load), 6) AS imbalance FROM v{v}" for k, v in (("static", f"s{t}"), ("share", f"f{t}"), ("strips", f"p{t}"))]
    return o.join(ctes, " UNION ALL ".join(picks))


@query("w12_skewed_drift", _skewed_sql())
def w12_skewed_drift(spark, sf):
    cut, rows = partition.share_cut(costs(spark, sf, "LQ"), 8), []
    for t in (0, 10):
        loads = costs(spark, sf, "LQ", t=t)
        for name, c in (("static", cut.reloaded(loads)), ("share", partition.share_cut(loads, 8)), ("strips", partition.strips(loads, [4, 4]))):
            rows.append((name, t, max(c.loads()), round(partition.imbalance(c.loads()), 6)))
    return spark.createDataFrame(rows, "policy string, t long, max_load long, imbalance double")


@query("w11_element_cost", o.join(
    [x for b in (0, 1, 10) for x in [(f"p{b}", o.particles("EV")), (f"l{b}", f"SELECT ti, tj, sum(w)::BIGINT AS cost FROM (SELECT (x * 32) // 2592000000000 AS ti, (y * 32) // 65536 AS tj, 1 AS w FROM p{b} UNION ALL SELECT (p_size * 32) // 64, ((((round(p_retailprice * 100)::BIGINT - 90000) % 16384) + 16384) % 16384 * 32) // 16384, {b} FROM part) GROUP BY 1, 2"), *o.prefix(str(b), 32, 32), *o.share(str(b), 32, 32, 8)]],
    " UNION ALL ".join(f"SELECT {b}::BIGINT AS b, pid, x0, x1, y0, y1, load FROM v{b}" for b in (0, 1, 10)),
))
def w11_element_cost(spark, sf):
    """How the cut moves as elements cost more."""
    from ..sources.tables import load

    grid = grid_of("EV")
    elements = mesh.part_elements(load(spark, sf, "part")).select("elem", (F.col("bx") * (grid.lx // 64)).alias("bx"), (F.col("by") * (grid.ly // 16_384)).alias("by"))
    once = tile_load(particles(spark, sf, "EV"), grid, elements)
    a, e = gather(once, grid, "particles"), gather(once, grid, "elements")
    rows = [(b, x.pid, *x.box, x.load) for b in (0, 1, 10) for x in partition.share_cut(LoadMap(a.cost + b * e.cost), 8).leaves]
    return spark.createDataFrame(rows, "b long, pid long, x0 long, x1 long, y0 long, y1 long, load long")


@query("w_tile_sweep", o.join([x for k in SIZES for x in _loads(n=k, tag=f"n{k}") + o.share(f"n{k}", k, k, 32, out=f"s{k}") + o.strips(f"n{k}", k, k, [8] * 4, out=f"r{k}") + o.even(f"e{k}", k, k, 4, 8) + o.reload(f"n{k}", f"e{k}", f"w{k}")], " UNION ALL ".join(f"SELECT {k}::BIGINT AS k, '{name}' AS policy, max(load)::BIGINT AS max_load, round(max(load) / avg(load), 6) AS imbalance FROM v{v}{k}" for k in SIZES for name, v in (("share", "s"), ("strips", "r"), ("even", "w")))))
def w_tile_sweep(spark, sf):
    """Balance by tiles for 32 owners: few tiles for each owner cost balance."""
    fine, rows = costs(spark, sf, n=SIZES[-1]), []
    for k in SIZES:
        loads = coarser(fine, SIZES[-1] // k)
        for name, c in (("share", partition.share_cut(loads, 32)), ("strips", partition.strips(loads, [8] * 4)), ("even", partition.even_tiles(grid_of("EV", k), 4, 8, loads))):
            rows.append((k, name, max(c.loads()), round(partition.imbalance(c.loads()), 6)))
    return spark.createDataFrame(rows, "k long, policy string, max_load long, imbalance double")

