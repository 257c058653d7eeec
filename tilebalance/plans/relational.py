"""Queries of the operators around the methods: scans, predicates, joins, aggregates, windows, sets, functions, streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import sql as functions
from ..functions.exprs import interleave, snapshot
from ..operators import diffusion, fields, mesh, metrics, partition, pic, placement
from ..operators.cost import tile_load
from ..operators.grid import Grid, div, line_sums, locate, neighbours, prefix_table, tile_x, tile_y, tiles
from ..oracle import text as o
from ..sources.tables import grid_of, json_weight, load, particles
from ..streaming import streams
from .methods import _BASE, _E44, _J, _OWN, _T, _cut0, _loads, _owner_map, at, costs
from .registry import query

_TABLES = {
    "region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey",
    "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id",
}

for _name, _key in _TABLES.items():

    @query(f"scan_{_name}", f"SELECT count(*) AS n, sum({_key})::BIGINT AS keys, min({_key})::BIGINT AS first, max({_key})::BIGINT AS last FROM {_name}")
    def scan(spark, sf, name=_name, key=_key):
        k = F.col(key).cast("long")
        return load(spark, sf, name).agg(F.count("*").alias("n"), F.sum(k).alias("keys"), F.min(k).alias("first"), F.max(k).alias("last"))


@query("gen_quads", o.join([("n", f"SELECT ((x * 16) // 2592000000000 * 16 + (y * 16) // 65536) * 2 AS elem, count(*) AS n FROM ({o.particles('EV')}) GROUP BY 1")], "SELECT ((i * 16 + j) * 2)::BIGINT AS elem, 'quad' AS kind, (4 * (i * 2592000000000 // 16) + 2 * 162000000000) // 4 AS bx, (4 * (j * 65536 // 16) + 2 * 4096) // 4 AS by, coalesce(n.n, 0) AS n FROM range(16) a(i) CROSS JOIN range(16) b(j) LEFT JOIN n ON n.elem = (i * 16 + j) * 2"))
def gen_quads(spark, sf):
    """Every quad, with the number of particles in it."""
    grid = grid_of("EV", 16)
    held = mesh.locate_quads(particles(spark, sf, "EV"), 16, grid).groupBy("elem").agg(F.count("*").alias("n"))
    return mesh.quads(spark, 16, grid).join(held, "elem", "left").select("elem", "kind", "bx", "by", F.coalesce("n", F.lit(0)).alias("n"))


# projections and predicates


@query("proj_fixed_point", o.join([("p", o.particles("EV"))], "SELECT * FROM p"))
def proj_fixed_point(spark, sf):
    return particles(spark, sf, "EV")


for _adapter in ("LP", "LQ", "OR", "EM", "DOC", "PG", "CV"):

    @query(f"proj_{_adapter.lower()}", o.join([("p", o.particles(_adapter))], "SELECT * FROM p"))
    def proj(spark, sf, adapter=_adapter):
        return particles(spark, sf, adapter)


_PLACED = [("p", o.particles("EV")), ("t", f"SELECT *, {_T} AS ti, {_J} AS tj FROM p")]


@query("filter_subdomain", o.join(_PLACED, "SELECT pid_key, ti, tj FROM t WHERE ti >= 8 AND ti < 16 AND tj >= 0 AND tj < 2"))
def filter_subdomain(spark, sf):
    return locate(particles(spark, sf, "EV"), grid_of("EV")).where("ti >= 8 AND ti < 16 AND tj >= 0 AND tj < 2").select("pid_key", "ti", "tj")


@query("filter_leavers", o.join(_BASE + [("pp", o.particles("EV", 1))], f"SELECT p.pid_key FROM p {_OWN('')} JOIN pp q ON q.pid_key = p.pid_key WHERE NOT ((q.x * 32) // 2592000000000 BETWEEN x0 AND x1 - 1 AND (q.y * 32) // 65536 BETWEEN y0 AND y1 - 1)"))
def filter_leavers(spark, sf):
    grid, cut = grid_of("EV"), _cut0(spark, sf)
    return placement.leavers(pic.push(placement.fixed_owner(particles(spark, sf, "EV"), cut, grid), grid), cut.frame(spark), grid).select("pid_key")


@query("filter_species", o.join([("p", o.particles("EV"))], "SELECT species, count(*) AS n, sum(vx)::BIGINT AS vx FROM p WHERE species IN (0, 1) GROUP BY 1"))
def filter_species(spark, sf):
    return particles(spark, sf, "EV").where(F.col("species").isin(0, 1)).groupBy("species").agg(F.count("*").alias("n"), F.sum("vx").alias("vx"))


@query("filter_event_types", "SELECT event_id, CASE WHEN event_type = 'purchase' THEN 2 WHEN event_type LIKE 'c%' THEN 1 ELSE 0 END::BIGINT AS class FROM events WHERE regexp_matches(event_type, '^[a-p]') AND value BETWEEN 1 AND 100 AND event_id % 4 = 0")
def filter_event_types(spark, sf):
    kind = F.when(F.col("event_type") == "purchase", 2).when(F.col("event_type").startswith("c"), 1).otherwise(0)
    return load(spark, sf, "events").where(F.col("event_type").rlike("^[a-p]") & F.col("value").between(1, 100) & (F.pmod("event_id", F.lit(4)) == 0)).select("event_id", kind.cast("long").alias("class"))


# joins


@query("join_owner_broadcast", o.join(_BASE, f"SELECT p.pid_key, v.pid AS owner FROM p {_OWN('')}"))
def join_owner_broadcast(spark, sf):
    grid = grid_of("EV")
    return placement.join_owner(locate(particles(spark, sf, "EV"), grid), partition.expand(_cut0(spark, sf).frame(spark)), grid).select("pid_key", "owner")


@query("join_fields_shuffle", o.join([("p", o.particles("EV")), ("d", f"SELECT {_T} AS ti, {_J} AS tj, count(*) AS c FROM p GROUP BY 1, 2")], f"SELECT p.pid_key, d.c AS charge FROM p JOIN d ON d.ti = {_T} AND d.tj = {_J}"))
def join_fields_shuffle(spark, sf):
    grid = grid_of("EV")
    df = locate(particles(spark, sf, "EV"), grid)
    return df.join(pic.deposit(df, grid).select("ti", "tj", "charge").hint("SHUFFLE_HASH"), ["ti", "tj"]).select("pid_key", "charge")


@query("join_before_after", o.join([("p", o.particles("EV")), ("q", o.particles("EV", 7))], "SELECT pid_key, p.x AS x0, q.x AS x1 FROM p JOIN q USING (pid_key)"))
def join_before_after(spark, sf):
    df = particles(spark, sf, "EV")
    return df.select("pid_key", F.col("x").alias("x0")).join(pic.push(df, grid_of("EV"), 7).select("pid_key", F.col("x").alias("x1")).hint("MERGE"), "pid_key")


@query("join_rect_theta", o.join(_BASE, f"SELECT p.pid_key, v.pid AS owner FROM p {_OWN('')}"))
def join_rect_theta(spark, sf):
    grid = grid_of("EV")
    boxes = F.broadcast(_cut0(spark, sf).frame(spark))  # a row for each owner
    located = locate(particles(spark, sf, "EV"), grid)
    inside = (located["ti"] >= boxes["x0"]) & (located["ti"] < boxes["x1"]) & (located["tj"] >= boxes["y0"]) & (located["tj"] < boxes["y1"])
    return located.join(boxes, inside).select("pid_key", F.col("pid").alias("owner"))


@query("join_neighbour_tiles", o.join(_PLACED + [("l", "SELECT ti, tj, count(*) AS c FROM t GROUP BY 1, 2")], "SELECT l.ti, l.tj, sum(q.c)::BIGINT AS beside FROM l JOIN (VALUES (1, 0), (-1, 0), (0, 1), (0, -1)) d(a, b) ON true JOIN l q ON q.ti = (l.ti + a + 32) % 32 AND q.tj = (l.tj + b + 32) % 32 GROUP BY 1, 2"))
def join_neighbour_tiles(spark, sf):
    grid = grid_of("EV")
    loads = tile_load(particles(spark, sf, "EV"), grid).select("ti", "tj", "cost")
    other = loads.select(F.col("ti").alias("ni"), F.col("tj").alias("nj"), F.col("cost").alias("c"))
    return neighbours(loads, grid).join(other, ["ni", "nj"]).groupBy("ti", "tj").agg(F.sum("c").alias("beside"))


@query("join_asof_mapping", "SELECT event_id, max(m.t)::BIGINT AS mapping FROM events JOIN (VALUES (0), (5), (11), (23)) m(t) ON m.t <= date_diff('day', DATE '2024-01-01', ts::DATE) GROUP BY event_id")
def join_asof_mapping(spark, sf):
    """The last of the mappings made by an event's day; the list of mappings is as short as the run's rebalances."""
    made = spark.createDataFrame([(0,), (5,), (11,), (23,)], "t long")
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01"))
    times = made.agg(F.array_sort(F.collect_list("t")).alias("times"))
    rows = load(spark, sf, "events").select("event_id", day.cast("long").alias("day")).join(F.broadcast(times))
    return rows.select("event_id", F.array_max(F.filter("times", lambda t: t <= F.col("day"))).alias("mapping")).where("mapping IS NOT NULL")


_DOCS = "SELECT (x * 32) // 65536 AS ti, (y * 32) // 32 AS tj, sum(weight)::BIGINT AS docs FROM pd GROUP BY 1, 2"
_PAGES = "SELECT (x * 32) // 65536 AS ti, (y * 32) // 65536 AS tj, sum(weight)::BIGINT AS pages FROM pp GROUP BY 1, 2"


@query("join_full_loads", o.join([("pd", o.particles("DOC")), ("pp", o.particles("PG")), ("a", _DOCS), ("b", _PAGES)], "SELECT ti, tj, coalesce(docs, 0) AS docs, coalesce(pages, 0) AS pages FROM a FULL JOIN b USING (ti, tj)"))
def join_full_loads(spark, sf):
    one = lambda a, to: tile_load(particles(spark, sf, a), grid_of(a), weight="weight").select("ti", "tj", F.col("cost").alias(to))
    return one("DOC", "docs").join(one("PG", "pages"), ["ti", "tj"], "full").select("ti", "tj", F.coalesce("docs", F.lit(0)).alias("docs"), F.coalesce("pages", F.lit(0)).alias("pages"))


for _kind, _in in (("semi", "IN"), ("anti", "NOT IN")):

    @query(f"join_{_kind}_tiles", o.join(_PLACED, f"SELECT i::BIGINT AS ti, j::BIGINT AS tj FROM range(32) a(i) CROSS JOIN range(32) b(j) WHERE (i, j) {_in} (SELECT (ti, tj) FROM t)"))
    def occupied(spark, sf, kind=_kind):
        grid = grid_of("EV")
        return tiles(spark, grid).join(tile_load(particles(spark, sf, "EV"), grid).select("ti", "tj"), ["ti", "tj"], f"left_{kind}")


@query("join_cross_candidates", o.join(_BASE, "SELECT v.pid, q::BIGINT AS q, s.s FROM v, LATERAL (SELECT unnest(range(x0 + 1, x1)) AS q) u JOIN s ON s.i = u.q AND s.j = 32"))
def join_cross_candidates(spark, sf):
    """Every inner line of every rectangle, with the running cost to it."""
    grid = grid_of("EV")
    lines = prefix_table(tile_load(particles(spark, sf, "EV"), grid), grid).where(F.col("j") == grid.m).select(F.col("i").alias("q"), "s")
    candidates = _cut0(spark, sf).frame(spark).where("x1 - x0 > 1").select("pid", F.explode(F.sequence(F.col("x0") + 1, F.col("x1") - 1)).alias("q"))
    return candidates.join(lines, "q").select("pid", "q", "s")


@query("join_lateral_top", o.join(_BASE + [("m", _owner_map("")), ("r", "SELECT m.pid, l.ti, l.tj, l.cost, row_number() OVER (PARTITION BY m.pid ORDER BY l.cost DESC, l.ti, l.tj) AS k FROM m JOIN l USING (ti, tj)")], "SELECT pid, ti, tj, cost FROM r WHERE k = 1"))
def join_lateral_top(spark, sf):
    grid = grid_of("EV")
    loads = tile_load(particles(spark, sf, "EV"), grid).select("ti", "tj", "cost")
    inside = "l.ti >= b.x0 AND l.ti < b.x1 AND l.tj >= b.y0 AND l.tj < b.y1"
    top = f"SELECT min(struct(-l.cost AS c, l.ti AS ti, l.tj AS tj)) AS top FROM {{loads}} l WHERE {inside}"
    return spark.sql(f"SELECT b.pid, t.top.ti, t.top.tj, -t.top.c AS cost FROM {{boxes}} b, LATERAL ({top}) t WHERE t.top IS NOT NULL", boxes=_cut0(spark, sf).frame(spark), loads=loads)


@query(
    "join_star_load",
    "SELECT r_name AS region, l_returnflag AS flag, count(*) AS load, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS cents FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey WHERE o_orderdate >= TIMESTAMP '1996-01-01' GROUP BY 1, 2",
)
def join_star_load(spark, sf):
    lines, orders = load(spark, sf, "lineitem"), load(spark, sf, "orders").where("o_orderdate >= TIMESTAMP_NTZ'1996-01-01'")
    customer, nation, region = (load(spark, sf, t) for t in ("customer", "nation", "region"))
    star = lines.join(orders, F.col("o_orderkey") == F.col("l_orderkey")).join(customer, F.col("c_custkey") == F.col("o_custkey")).join(nation, F.col("n_nationkey") == F.col("c_nationkey")).join(region, F.col("r_regionkey") == F.col("n_regionkey"))
    return star.groupBy(F.col("r_name").alias("region"), F.col("l_returnflag").alias("flag")).agg(F.count("*").alias("load"), F.sum(F.round(F.col("l_extendedprice") * 100).cast("long")).alias("cents"))


# aggregates


@query("agg_tile_load", o.join(_loads(), "SELECT ti, tj, cost FROM l"))
def agg_tile_load(spark, sf):
    return tile_load(particles(spark, sf, "EV"), grid_of("EV")).select("ti", "tj", "cost")


@query("agg_tile_load_lp", o.join(_loads("LP"), "SELECT ti, tj, cost FROM l"))
def agg_tile_load_lp(spark, sf):
    return tile_load(particles(spark, sf, "LP"), grid_of("LP")).select("ti", "tj", "cost")


@query("agg_deposit", o.join(_PLACED, "SELECT species, ti, sum(weight)::BIGINT AS charge, sum(weight * vx)::BIGINT AS jx FROM t GROUP BY 1, 2"))
def agg_deposit(spark, sf):
    return locate(particles(spark, sf, "EV"), grid_of("EV")).groupBy("species", "ti").agg(F.sum("weight").alias("charge"), F.sum(F.col("weight") * F.col("vx")).alias("jx"))


@query("agg_line_array", o.join(_loads(), "SELECT ti, array_to_string(list(cost ORDER BY tj), ',') AS line FROM l GROUP BY ti"))
def agg_line_array(spark, sf):
    loads = tile_load(particles(spark, sf, "EV"), grid_of("EV"))
    line = F.transform(F.array_sort(F.collect_list(F.struct("tj", "cost"))), lambda x: x["cost"].cast("string"))
    return loads.groupBy("ti").agg(F.array_join(line, ",").alias("line"))


@query("agg_footprint", o.join(_BASE + [("pp", o.particles("EV", 10))], f"SELECT v.pid, count(DISTINCT {_T} * 32 + {_J}) AS tiles_seen FROM pp p {_OWN('')} GROUP BY 1"))
def agg_footprint(spark, sf):
    grid = grid_of("EV")
    return metrics.footprint(placement.site_owner(at(spark, sf, t=10), _cut0(spark, sf), grid), grid)


@query("agg_footprint_approx")
def agg_footprint_approx(spark, sf):
    """Rows only: within 5 % of agg_footprint."""
    grid = grid_of("EV")
    return metrics.footprint(placement.site_owner(at(spark, sf, t=10), _cut0(spark, sf), grid), grid, approximate=True)


@query("agg_load_stats", o.join(_loads(), "SELECT tj, count(*) AS n, sum(cost)::BIGINT AS total, min(cost) AS least, max(cost) AS most, round(avg(cost), 6) AS mean, round(stddev_samp(cost), 6) AS deviation, round(regr_slope(cost, ti), 6) AS slope, arg_max(ti, (cost, -ti)) AS at, round(quantile_cont(cost, 0.5), 6) AS middle, bool_and(cost > 0) AS filled FROM l GROUP BY tj HAVING count(*) > 2"))
def agg_load_stats(spark, sf):
    c = F.col("cost")
    loads = tile_load(particles(spark, sf, "EV"), grid_of("EV"))
    return loads.groupBy("tj").agg(
        F.count("*").alias("n"), F.sum(c).alias("total"), F.min(c).alias("least"), F.max(c).alias("most"), F.round(F.avg(c), 6).alias("mean"), F.round(F.stddev_samp(c), 6).alias("deviation"),
        F.round(F.regr_slope(c, "ti"), 6).alias("slope"), F.max_by("ti", F.struct(c, -F.col("ti"))).alias("at"), F.round(F.percentile(c, F.lit(0.5)), 6).alias("middle"), F.bool_and(c > 0).alias("filled"),
    ).where("n > 2")


_GROUPS = o.join(_BASE, f"SELECT v.pid, p.species, e.event_type, count(*) AS load FROM p {_OWN('')} JOIN events e ON e.event_id = p.pid_key GROUP BY {{}}")


def _tagged(spark, sf):
    df = placement.site_owner(particles(spark, sf, "EV"), _cut0(spark, sf), grid_of("EV"), "pid")
    return df.join(load(spark, sf, "events").select(F.col("event_id").alias("pid_key"), "event_type"), "pid_key").select("pid", "species", "event_type")


@query("agg_cube_load", _GROUPS.format("CUBE (v.pid, p.species, e.event_type)"))
def agg_cube_load(spark, sf):
    return _tagged(spark, sf).cube("pid", "species", "event_type").agg(F.count("*").alias("load"))


@query("agg_grouping_sets", _GROUPS.format("GROUPING SETS ((v.pid, p.species), (e.event_type), ())").replace("v.pid, p.species, e.event_type,", "v.pid, p.species, e.event_type,", 1))
def agg_grouping_sets(spark, sf):
    df = _tagged(spark, sf)
    return df.groupingSets([[df["pid"], df["species"]], [df["event_type"]], []], "pid", "species", "event_type").agg(F.count("*").alias("load")).select("pid", "species", "event_type", "load")


@query("agg_rollup_tiles", o.join(_PLACED, "SELECT ti // 8 AS coarse, ti // 2 AS middle, ti, count(*) AS load FROM t GROUP BY ROLLUP (ti // 8, ti // 2, ti)".replace("SELECT ti // 8 AS coarse, ti // 2 AS middle, ti,", "SELECT a AS coarse, b AS middle, c AS ti,").replace("FROM t GROUP BY ROLLUP (ti // 8, ti // 2, ti)", "FROM (SELECT ti // 8 AS a, ti // 2 AS b, ti AS c FROM t) GROUP BY ROLLUP (a, b, c)")))
def agg_rollup_tiles(spark, sf):
    """A pyramid of tiles along x: loads of 4, 16 and 32 columns and of all."""
    df = locate(particles(spark, sf, "EV"), grid_of("EV")).select(div(F.col("ti"), 8).alias("coarse"), div(F.col("ti"), 2).alias("middle"), "ti")
    return df.rollup("coarse", "middle", "ti").agg(F.count("*").alias("load"))


@query("agg_pivot_matrix", o.join(_BASE, f"SELECT v.pid, count(*) FILTER (WHERE p.species = 0) AS even, count(*) FILTER (WHERE p.species = 1) AS odd FROM p {_OWN('')} GROUP BY 1"))
def agg_pivot_matrix(spark, sf):
    df = placement.site_owner(particles(spark, sf, "EV"), _cut0(spark, sf), grid_of("EV"), "pid")
    return df.withColumn("beam", F.when(F.col("species") == 0, "even").otherwise("odd")).groupBy("pid").pivot("beam", ["even", "odd"]).agg(F.count(F.lit(1))).na.fill(0)


@query("agg_filtered", o.join(_BASE + [("pp", o.particles("EV", 10))], f"SELECT v.pid, count(*) AS n, count(*) FILTER (WHERE NOT ((q.x * 32) // 2592000000000 BETWEEN x0 AND x1 - 1 AND (q.y * 32) // 65536 BETWEEN y0 AND y1 - 1)) AS leavers FROM p {_OWN('')} JOIN pp q ON q.pid_key = p.pid_key GROUP BY 1"))
def agg_filtered(spark, sf):
    grid, cut = grid_of("EV"), _cut0(spark, sf)
    df = placement.site_owner(pic.push(placement.fixed_owner(particles(spark, sf, "EV"), cut, grid), grid, 10), cut, grid, "now")
    return df.groupBy(F.col("owner").alias("pid")).agg(F.count("*").alias("n"), F.count_if(F.col("owner") != F.col("now")).alias("leavers"))


# windows and orders


@query("win_prefix_2d", o.join(_loads(), "SELECT i::BIGINT AS i, j::BIGINT AS j, s FROM s"))
def win_prefix_2d(spark, sf):
    grid = grid_of("EV")
    return prefix_table(tile_load(particles(spark, sf, "EV"), grid), grid)


@query("win_rank_tiles", o.join(_loads(), "SELECT ti, tj, row_number() OVER w AS n, rank() OVER v AS r, dense_rank() OVER v AS d, round(percent_rank() OVER v, 6) AS p FROM l WINDOW w AS (PARTITION BY ti ORDER BY cost DESC, tj), v AS (PARTITION BY ti ORDER BY cost DESC)"))
def win_rank_tiles(spark, sf):
    w, v = Window.partitionBy("ti").orderBy(F.desc("cost"), "tj"), Window.partitionBy("ti").orderBy(F.desc("cost"))
    loads = tile_load(particles(spark, sf, "EV"), grid_of("EV"))
    long = lambda c: c.cast("long")
    return loads.select("ti", "tj", long(F.row_number().over(w)).alias("n"), long(F.rank().over(v)).alias("r"), long(F.dense_rank().over(v)).alias("d"), F.round(F.percent_rank().over(v), 6).alias("p"))


@query("win_ntile_baseline", o.join(_loads(), "SELECT ti, tj, ntile(8) OVER (ORDER BY ti, tj) AS part FROM l"))
def win_ntile_baseline(spark, sf):
    loads = tile_load(particles(spark, sf, "EV"), grid_of("EV"))
    return loads.select("ti", "tj", F.ntile(8).over(Window.orderBy("ti", "tj")).cast("long").alias("part"))


@query("win_lag_load", o.join(_loads(), "SELECT ti, tj, cost - lag(cost, 1, 0) OVER w AS change, lead(cost) OVER w AS ahead, first_value(cost) OVER w AS first, nth_value(cost, 2) OVER w AS second FROM l WINDOW w AS (PARTITION BY ti ORDER BY tj)"))
def win_lag_load(spark, sf):
    w = Window.partitionBy("ti").orderBy("tj")
    loads = tile_load(particles(spark, sf, "EV"), grid_of("EV"))
    return loads.select("ti", "tj", (F.col("cost") - F.lag("cost", 1, 0).over(w)).alias("change"), F.lead("cost").over(w).alias("ahead"), F.first("cost").over(w).alias("first"), F.nth_value("cost", 2).over(w).alias("second"))


@query("win_running_max", o.join(_loads(), "SELECT ti, tj, max(cost) OVER (PARTITION BY ti ORDER BY tj) AS most FROM l"))
def win_running_max(spark, sf):
    return tile_load(particles(spark, sf, "EV"), grid_of("EV")).select("ti", "tj", F.max("cost").over(Window.partitionBy("ti").orderBy("tj")).alias("most"))


@query("win_moving_avg", "SELECT d AS day, event_type, round(avg(n) OVER (PARTITION BY event_type ORDER BY d RANGE BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS smooth FROM (SELECT date_diff('day', DATE '2024-01-01', ts::DATE) AS d, event_type, count(*) AS n FROM events GROUP BY 1, 2)")
def win_moving_avg(spark, sf):
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01")).cast("long").alias("day")
    per = load(spark, sf, "events").groupBy(day, "event_type").agg(F.count("*").alias("n"))
    return per.select("day", "event_type", F.round(F.avg("n").over(Window.partitionBy("event_type").orderBy("day").rangeBetween(-2, 0)), 6).alias("smooth"))


@query("topk_tiles", o.join(_loads(), "SELECT ti, tj, cost FROM l ORDER BY cost DESC, ti, tj LIMIT 10"))
def topk_tiles(spark, sf):
    return tile_load(particles(spark, sf, "EV"), grid_of("EV")).select("ti", "tj", "cost").orderBy(F.desc("cost"), "ti", "tj").limit(10)


# sets

_TWO = _BASE + _loads(t=50, tag="t") + o.share("t", 32, 32, 8) + [("m", _owner_map("")), ("mt", _owner_map("t"))]


def _maps(spark, sf):
    return (partition.expand(partition.share_cut(costs(spark, sf, t=t), 8).frame(spark)) for t in (0, 50))


@query("set_union_move", o.join(_BASE + [("pp", o.particles("EV", 10))], f"SELECT p.pid_key, v.pid AS owner FROM pp p {_OWN('')}"))
def set_union_move(spark, sf):
    grid, cut = grid_of("EV"), _cut0(spark, sf)
    df = placement.site_owner(pic.push(placement.site_owner(particles(spark, sf, "EV"), cut, grid, "owner0"), grid, 10), cut, grid)
    return placement.move(df, 8).select("pid_key", "owner")


@query("set_intersect_owner", o.join(_TWO, "SELECT * FROM m INTERSECT SELECT * FROM mt"))
def set_intersect_owner(spark, sf):
    a, b = _maps(spark, sf)
    return a.intersect(b)


@query("set_except_owner", o.join(_TWO, "SELECT * FROM m EXCEPT SELECT * FROM mt"))
def set_except_owner(spark, sf):
    a, b = _maps(spark, sf)
    return a.exceptAll(b)


# functions


def _bits(a: str, b: str, bits: int = 16) -> str:
    return " + ".join(f"(((({v}) >> {k}) & 1) << {2 * k + s})" for k in range(bits) for s, v in ((0, a), (1, b)))


@query("fn_zorder_key", o.join([("p", o.particles("EV")), ("q", f"SELECT pid_key, {_T} AS i, {_J} AS j FROM p")], f"SELECT pid_key, i::BIGINT AS ti, j::BIGINT AS tj, ({_bits('i', 'j')})::BIGINT AS z FROM q"))
def fn_zorder_key(spark, sf):
    """The key of each particle's tile."""
    return locate(particles(spark, sf, "EV"), grid_of("EV")).select("pid_key", "ti", "tj", interleave(F.col("ti"), F.col("tj")).alias("z"))


@query("fn_json_weight", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
def fn_json_weight(spark, sf):
    return load(spark, sf, "events").select("event_id", json_weight().alias("k"))


@query("fn_polygon_barycentre", o.join([("p", o.particles("EV"))], "SELECT pid_key AS elem, CASE WHEN pid_key % 2 = 0 THEN (4 * x + 12288) // 4 ELSE (3 * x + 12288) // 3 END AS bx, CASE WHEN pid_key % 2 = 0 THEN (4 * y + 192) // 4 ELSE (3 * y + 64) // 3 END AS by FROM p"))
def fn_polygon_barycentre(spark, sf):
    """Quads and triangles that begin at the particles."""
    v = lambda a, b: F.struct((F.col("x") + a).alias("x"), (F.col("y") + b).alias("y"))
    three = [v(0, 0), v(4096, 0), v(8192, 64)]
    verts = F.when(F.col("pid_key") % 2 == 0, F.array(*three, v(0, 128))).otherwise(F.array(*three))
    return mesh.with_barycentre(particles(spark, sf, "EV").select(F.col("pid_key").alias("elem"), verts.alias("verts"))).select("elem", "bx", "by")


@query("fn_date_axis", "SELECT o_orderkey, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS day, date_trunc('month', o_orderdate)::DATE::VARCHAR AS month FROM orders")
def fn_date_axis(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01")).cast("long").alias("day"), F.to_date(F.date_trunc("month", "o_orderdate")).cast("string").alias("month"))


@query("fn_map_snapshot", o.join(_BASE, "SELECT pid, load FROM v"))
def fn_map_snapshot(spark, sf):
    one = _cut0(spark, sf).frame(spark).agg(snapshot().alias("loads"))
    return one.select(F.explode("loads").alias("pid", "load"))


# functions for SQL users


@query("sqludf_tile_of", o.join([("p", o.particles("EV"))], f"SELECT pid_key, {_T} AS ti FROM p"))
def sqludf_tile_of(spark, sf):
    functions.register(spark)
    return particles(spark, sf, "EV").select("pid_key", F.call_function("tile_of", F.col("x"), F.lit(32).cast("long"), F.lit(2_592_000_000_000)).alias("ti"))


@query("udtf_share_cut", o.join(_BASE, "SELECT pid, x0, x1, y0, y1, height, load FROM v"))
def udtf_share_cut(spark, sf):
    functions.register(spark)
    loads = tile_load(particles(spark, sf, "EV"), grid_of("EV")).select("ti", "tj", "cost")
    return spark.sql("SELECT * FROM share_cut_udtf(TABLE({loads}) WITH SINGLE PARTITION, 32, 32, 8)", loads=loads)


@query("udtf_pair_schedule", "SELECT * FROM (VALUES (5::BIGINT, 1::BIGINT, 0::BIGINT, 1::BIGINT), (5, 1, 2, 3), (5, 2, 1, 2), (5, 2, 3, 4), (2, 1, 0, 1), (2, 2, 0, 1)) t(size, t, upper, lower)")
def udtf_pair_schedule(spark, sf):
    functions.register(spark)
    return spark.sql("SELECT CAST(s.size AS BIGINT) AS size, CAST(s.t AS BIGINT) AS t, p.upper, p.lower FROM (VALUES (5, 1), (5, 2), (2, 1), (2, 2)) s(size, t), LATERAL pair_schedule(s.size, s.t) p")


@query("udaf_imbalance", o.join(_loads(), "SELECT ti, round(max(cost) / avg(cost), 6) AS imbalance FROM l GROUP BY ti"))
def udaf_imbalance(spark, sf):
    return tile_load(particles(spark, sf, "EV"), grid_of("EV")).groupBy("ti").agg(F.round(functions.imbalance_of(F.col("cost").cast("double")), 6).alias("imbalance"))


@query("arrow_rotation", o.join([("p", o.particles("EV"))], "SELECT pid_key, round(cos(0.5) * vx + sin(0.5) * vy)::BIGINT AS vx, round(cos(0.5) * vy - sin(0.5) * vx)::BIGINT AS vy FROM p"))
def arrow_rotation(spark, sf):
    return particles(spark, sf, "EV").select("pid_key", functions.rotated("vx", "vy", 0.5).alias("v")).select("pid_key", "v.vx", "v.vy")


@query("pandas_column_exchange", o.join(_loads() + o.strips("", 32, 32, [4, 4], out="z0") + o.strip_step("", "z0", "z1", 1, 32, 32), "SELECT r.c AS col, r.k AS pos, r.q AS line FROM rz1 r JOIN kz1 k ON k.c = r.c WHERE r.k BETWEEN 1 AND k.size - 1"))
def pandas_column_exchange(spark, sf):
    """Each column's pairs in a task of its own, from line sums alone."""
    loads = costs(spark, sf)
    cut = partition.strips(loads, [4, 4])
    edges = [cut.leaves[0], cut.leaves[4]]
    rows = tile_load(particles(spark, sf, "EV"), grid_of("EV")).select(F.when(F.col("ti") < edges[0].x1, 0).otherwise(1).cast("long").alias("col"), F.col("tj").alias("line"), "cost")
    dense = spark.range(2).select(F.col("id").alias("col")).crossJoin(spark.range(32).select(F.col("id").alias("line")))
    lines = dense.join(rows.groupBy("col", "line").agg(F.sum("cost").alias("w")), ["col", "line"], "left").select("col", "line", F.coalesce("w", F.lit(0)).alias("w"))
    borders = spark.createDataFrame([(c, k, cut.leaves[4 * c + k].y0) for c in (0, 1) for k in (1, 2, 3)], "col long, pos long, line long")
    return functions.column_exchange(lines, borders, 1)


# streams: bounded input, read to its end

_XY = f"{o.mod('epoch_us(ts) - 1704067200000000', 2592000000000)} AS x, {o.mod('round(value * 100)::BIGINT', 65536)} AS y"


def _events(spark, sf):
    return streams.events(spark, f"{sf}/events.parquet")


@query("stream_tumbling_load", f"SELECT epoch(date_trunc('day', ts))::BIGINT AS start_s, (x * 32) // 2592000000000 AS ti, (y * 32) // 65536 AS tj, count(*) AS load FROM (SELECT ts, {_XY} FROM events) GROUP BY 1, 2, 3")
def stream_tumbling_load(spark, sf):
    return streams.collected(streams.tumbling(_events(spark, sf), grid_of("EV")))


@query("stream_sliding_load", "SELECT epoch(date_trunc('day', ts))::BIGINT - 86400 * k AS start_s, event_type, count(*) AS load FROM events CROSS JOIN range(3) t(k) GROUP BY 1, 2")
def stream_sliding_load(spark, sf):
    return streams.collected(streams.sliding(_events(spark, sf)))


@query(
    "stream_session_load",
    "SELECT user_id, min(us)::BIGINT AS start_us, max(us)::BIGINT + 21600000000 AS end_us, count(*) AS load FROM (SELECT user_id, us, sum(new) OVER (PARTITION BY user_id ORDER BY us, event_id) AS s FROM (SELECT user_id, event_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 21600000000 THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s",
)
def stream_session_load(spark, sf):
    return streams.collected(streams.sessions(_events(spark, sf)))


@query("stream_owner_join", o.join(_BASE, f"SELECT v.pid, count(*) AS load FROM p {_OWN('')} GROUP BY 1"))
def stream_owner_join(spark, sf):
    owner = partition.expand(_cut0(spark, sf).frame(spark))
    return streams.collected(streams.owned(_events(spark, sf), owner, grid_of("EV")).groupBy("pid").agg(F.count("*").alias("load")))


@query("stream_follow_ups", "SELECT a.event_id AS first_id, b.event_id AS then_id, a.user_id FROM events a JOIN events b ON b.user_id = a.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_follow_ups(spark, sf):
    return streams.collected(streams.follow_ups(_events(spark, sf), "click"), "append")


@query("stream_once", "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1")
def stream_once(spark, sf):
    rows = streams.collected(streams.once(_events(spark, sf)).select("event_id", "event_type"), "append")
    return rows.groupBy("event_type").agg(F.count("*").alias("n"))


# lines of tiles and prescribed fields


@query("grid_line_sums", o.join(_loads(), "SELECT ti, sum(cost)::BIGINT AS cost FROM l GROUP BY 1"))
def grid_line_sums(spark, sf):
    return line_sums(tile_load(particles(spark, sf, "EV"), grid_of("EV")))


@query("field_prescribed", o.join(_loads(), "SELECT ti, tj, (ti - 16)::BIGINT AS fx, (2 * tj)::BIGINT AS fy, cost FROM l"))
def field_prescribed(spark, sf):
    """The field in every tile that holds particles, with their number."""
    grid = grid_of("EV")
    return fields.prescribed(spark, grid, F.col("ti") - 16, F.col("tj") * 2).join(tile_load(particles(spark, sf, "EV"), grid), ["ti", "tj"]).select("ti", "tj", "fx", "fy", "cost")


@query("met_volume", o.join(_E44, "SELECT a.pid AS a, b.pid AS b, (abs(a.load - b.load) // 6)::BIGINT AS tiles FROM ve a JOIN ve b ON b.pid = a.pid + 1"))
def met_volume(spark, sf):
    """Tiles of a cost of 3 between owners of equal blocks and the next ones."""
    w = {x.pid: x.load for x in partition.even_tiles(grid_of("EV"), 4, 4, costs(spark, sf)).leaves}
    return spark.createDataFrame([(a, a + 1, diffusion.volume(w[a], w[a + 1], 3)) for a in sorted(w) if a + 1 in w], "a long, b long, tiles long")


@query("tile_expressions", o.join([("p", o.particles("LQ"))], "SELECT (x * 32) // 16777216 AS ti, (y * 32) // 64 AS tj, count(*) AS n FROM p GROUP BY 1, 2"))
def tile_expressions(spark, sf):
    grid = grid_of("LQ")
    return particles(spark, sf, "LQ").groupBy(tile_x(grid).alias("ti"), tile_y(grid).alias("tj")).agg(F.count("*").alias("n"))
