"""Placement, phases, meshes, whole runs, streams, sources and sinks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilebalance import schema
from tilebalance.functions import sql as functions
from tilebalance.operators import fields, mesh, metrics, partition, pic, placement
from tilebalance.operators.cost import gather, tile_load
from tilebalance.operators.grid import Grid
from tilebalance.plans.methods import at, costs
from tilebalance.plans import relational  # noqa: F401  it registers its queries
from tilebalance.plans.registry import QUERIES
from tilebalance.plans.policy import Every, Never, Threshold, fresh_strips, full, neighbours, tether_or_full, tethered
from tilebalance.operators import diffusion
from tilebalance.operators.lineage import shared
from tilebalance.plans.simulate import Run, phases, run
from tilebalance.sources import sinks
from tilebalance.sources.tables import grid_of, particles, two_stream
from tilebalance.sources.twostream import TwoStream
from tilebalance.streaming import streams

SF = "/root/testdata/sf0.001"


def test_push_edges(spark):
    grid = Grid(4, 4, 16, 16)
    rows = spark.createDataFrame([(0, 15, 3, 1, 0, 1, 0), (1, 0, 3, -1, 0, 1, 1), (2, 8, 0, 0, -1, 1, 0)], schema.PARTICLE)
    got = {r["pid_key"]: (r["x"], r["y"]) for r in pic.push(rows, grid).collect()}
    assert got == {0: (0, 3), 1: (15, 3), 2: (8, 15)}
    walls = {r["pid_key"]: (r["x"], r["vx"], r["y"], r["vy"]) for r in pic.push(rows, Grid(4, 4, 16, 16, "reflect"), 2).collect()}
    assert walls == {0: (14, -1, 3, 0), 1: (1, 1, 3, 0), 2: (8, 0, 1, 1)}
    assert {r["pid_key"] for r in pic.push(rows, Grid(4, 4, 16, 16, "absorb")).collect()} == set()
    with pytest.raises(ValueError):
        Grid(0, 1, 1, 1)


def test_closed_form_equals_steps(spark):
    grid, df = grid_of("EV"), particles(spark, SF, "EV")
    once = df
    for _ in range(7):
        once = pic.push(once, grid)
    assert sorted(map(tuple, once.collect())) == sorted(map(tuple, pic.push(df, grid, 7).collect()))


def test_node_deposit_keeps_the_charge(spark):
    df = particles(spark, SF, "EV")
    got = pic.deposit(df, grid_of("EV"), "node").agg(F.sum("charge")).first()[0]
    assert got == 1000 * pic.UNIT**2
    field = fields.tile_gradient(pic.deposit(df, grid_of("EV")), grid_of("EV"))
    assert field.agg(F.sum("fx"), F.sum("fy")).first()[:] == (0, 0)


def test_placement(spark):
    grid, cut = grid_of("EV"), partition.share_cut(costs(spark, SF), 8)
    fixed = pic.push(placement.fixed_owner(particles(spark, SF, "EV"), cut, grid), grid, 50)
    site = placement.site_owner(at(spark, SF, t=50), cut, grid)
    table = placement.join_owner(at(spark, SF, t=50).transform(lambda d: pic.relocate(d, grid)), partition.expand(cut.frame(spark)), grid)
    assert sorted(map(tuple, site.select("pid_key", "owner").collect())) == sorted(map(tuple, table.select("pid_key", "owner").collect()))
    assert placement.leavers(site, cut.frame(spark), grid).isEmpty()
    # site owners share the occupied tiles out among them, fixed owners come to see the same ones
    seen = [metrics.footprint(x, grid).agg(F.sum("tiles_seen")).first()[0] for x in (fixed, site)]
    occupied = pic.relocate(site, grid).select("ti", "tj").distinct().count()
    assert seen[1] == occupied and seen[0] > 1.2 * seen[1]
    both = site.join(fixed.select("pid_key", F.col("owner").alias("owner0")), "pid_key")
    n = placement.migrations(both).agg(F.sum("n")).first()[0]
    assert n == placement.leavers(fixed, cut.frame(spark), grid).count() == both.where("owner <> owner0").count()
    dealt = placement.by_owner(site, 8).withColumn("p", F.spark_partition_id())
    assert dealt.where("p <> owner").isEmpty()
    assert placement.move(both, 8).count() == 1000


def test_meshes(spark):
    grid = Grid(16, 16, 1 << 12, 1 << 12)
    assert mesh.counts(mesh.quads(spark, 128, Grid(16, 16, 1 << 14, 1 << 14))).first()[:] == (16_384, 2 * 128 * 129, 16_641)
    tri = mesh.triangles(spark, 8, grid)
    assert mesh.counts(tri).first()[:] == (128, 3 * 64 + 16, 81)
    points = two_stream(spark, 500, grid.lx, grid.ly)
    for made in (tri, mesh.hybrid(spark, 8, grid), mesh.quads(spark, 8, grid)):
        assert mesh.locate_elements(points, made, grid).count() == 500  # every point is in one element
    assert sorted(map(tuple, mesh.locate_elements(points, mesh.quads(spark, 8, grid), grid).select("pid_key", "elem").collect())) != []
    shared(spark)
    parts = mesh.graph_cut(mesh.quads(spark, 8, grid), 4, rounds=3)
    sizes = [r["count"] for r in parts.groupBy("part").count().collect()]
    assert len(sizes) == 4 and sum(sizes) == 64 and max(sizes) <= 18
    cut = mesh.edge_cut(parts, mesh.adjacency(mesh.quads(spark, 8, grid))).first()
    assert cut["pairs"] == 112 and cut["cut"] < 40


def test_leapfrog_conserves(spark):
    grid = Grid(8, 8, 64, 64)
    start = fields.prescribed(spark, grid, F.col("ti"), F.col("tj")).select("ti", "tj", (F.col("ti") / 8.0).alias("ex"), (F.col("tj") / 8.0).alias("ey"), F.lit(0.0).alias("bz"))
    none = spark.createDataFrame([], "ti long, tj long, jx double, jy double")
    energies = [fields.energy(fields.leapfrog_quads(start, none, grid, 0.2, k)).first()[0] for k in (0, 2, 4)]
    assert all(0.4 * energies[0] < e < 1.6 * energies[0] for e in energies)


def test_cost_variants(spark):
    grid, df = grid_of("EV"), particles(spark, SF, "EV")
    whole = gather(tile_load(df, grid), grid).total
    rough = gather(tile_load(df, grid, sample=4), grid).total
    assert whole == 1000 and rough % 4 == 0 and abs(rough - whole) < 300
    with pytest.raises(ValueError):
        gather(tile_load(df, grid), Grid(1 << 10, 1 << 10, grid.lx, grid.ly))
    with pytest.raises(TypeError):
        schema.expect(df.drop("x"), schema.PARTICLE)


@pytest.mark.parametrize("placed", ["site", "fixed"])
def test_runs(spark, placed):
    grid, df = grid_of("EV"), particles(spark, SF, "EV")
    strips = lambda loads: partition.strips(loads, [4, 4])
    few = {"site": ((Never(), None), (Every(1, tether_or_full()), None), (Every(1, neighbours(2)), strips)), "fixed": ((Never(), None), (Every(2, tethered()), None), (Threshold(1.3, full), None), (Every(1, fresh_strips), strips))}
    for policy, initial in few[placed]:
        state, history = run(df, Run(grid, 8, 3, placed, policy, initial))
        rows = history.orderBy("t").collect()
        schema.expect(history, schema.STEP_METRIC)
        assert [r["t"] for r in rows] == [0, 1, 2, 3] and {r["particles"] for r in rows} == {1000}
        assert state.count() == 1000
        if isinstance(policy, Never):
            assert sum(r["tiles_moved"] for r in rows) == 0 and rows[-1]["syncs"] == 1
            if placed == "fixed":
                assert len({r["max_load"] for r in rows}) == 1 and rows[-1]["particles_moved"] == 0
        if placed == "site":
            cut_owner = state.where("owner is null")
            assert cut_owner.isEmpty()


def test_kicked_run(spark):
    grid = Grid(16, 4, 1 << 16, 1 << 16)
    state, history = run(two_stream(spark, 400, grid.lx, grid.ly, 1 << 8), Run(grid, 4, 2, "site", Every(1), kick=True))
    assert state.count() == 400 and history.count() == 3


def test_two_stream_growth(spark):
    """Beams drift apart and bunch: the field's energy does not die out, and charge stays."""
    from tilebalance.plans.workloads import w5_two_stream_energy

    rows = {r["t"]: r["energy"] for r in w5_two_stream_energy(spark, SF).collect()}
    assert len(rows) == 4 and all(e >= 0 for e in rows.values())
    made = spark.createDataFrame([(t, float(np.exp(0.3 * t))) for t in range(6)], "t long, energy double")
    assert abs(metrics.growth_rate(made).first()[0] - 0.3) < 1e-9


def test_data_source(spark):
    spark.dataSource.register(TwoStream)
    source = spark.read.format("two_stream").option("n", 1000).option("lx", 1 << 20).option("ly", 1 << 20)
    want = sorted(map(tuple, two_stream(spark, 1000).collect()))
    assert sorted(map(tuple, source.load().collect())) == want
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    try:
        part = source.option("pushdown", 1).load().where("x >= 300000 AND x < 500000 AND species = 1")
        assert sorted(map(tuple, part.collect())) == [r for r in want if 300000 <= r[1] < 500000 and r[6] == 1]
    finally:
        spark.conf.unset("spark.sql.python.filterPushdown.enabled")


def test_sinks(spark, tmp_path):
    grid, cut = grid_of("EV"), partition.share_cut(costs(spark, SF), 4)
    for t in (0, 1):
        sinks.write_snapshot(placement.site_owner(at(spark, SF, t=t), cut, grid), str(tmp_path / "snap"), t, grid, 4)
    assert sinks.read_snapshot(spark, str(tmp_path / "snap")).count() == 2000
    one = sinks.read_snapshot(spark, str(tmp_path / "snap"), 1, 2)
    assert one.count() == placement.site_owner(at(spark, SF, t=1), cut, grid).where("owner = 2").count()
    tree = cut.tree(spark)
    want = sorted(map(str, tree.collect()))
    for kind in ("csv", "json", "orc", "text"):
        sinks.write_plain(tree, str(tmp_path / kind), kind)
        assert sorted(map(str, sinks.read_plain(spark, str(tmp_path / kind), kind, schema.CUT_TREE).collect())) == want


def test_rows_of_streams_do_not_come_to_the_driver(spark, sf):
    """A table of the driver's memory is one relation of rows; these are files that Spark's tasks read."""
    for name in ("stream_once", "stream_session_load"):
        df = QUERIES[name](spark, sf)
        assert df.inputFiles() and "MemoryPlan" not in df._jdf.queryExecution().optimizedPlan().toString()
    stream = streams.events(spark, f"{sf}/events.parquet")
    none = streams.collected(stream.where("event_id < 0").select("event_id"), "append")
    assert none.columns == ["event_id"] and none.count() == 0


def test_streams(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts")
    for k in range(3):
        events.where(F.pmod("event_id", F.lit(3)) == k).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = streams.events(spark, str(tmp_path / "in"))
    balancer = streams.Rebalancer(grid_of("EV"), 8)
    streams.drained(streams.place(stream, grid_of("EV")), balancer, tmp_path / "ck1")
    assert [h[1] for h in balancer.history][-1] == 1000 and len(balancer.history) == 3
    before = list(balancer.history)
    balancer(streams.place(spark.read.parquet(str(tmp_path / "in")).withColumn("ts", F.col("ts").cast("timestamp")), grid_of("EV")), 2)  # a batch that comes again
    assert balancer.history == before
    owner = partition.expand(balancer.mapping().frame(spark))
    rows = []
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        loads = streams.owner_loads(streams.owned(streams.events(spark, str(tmp_path / "in")), owner, grid_of("EV")))
        q = loads.writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "ck2")).foreachBatch(lambda b, n: rows.extend(b.collect())).trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    last = {}
    for r in rows:
        last[r["owner"]] = max(last.get(r["owner"], 0), r["load"])
    assert sum(last.values()) == 1000 and any(r["signal"] for r in rows)


def test_late_rows_are_dropped(spark, tmp_path):
    schema_ = spark.read.parquet(f"{SF}/events.parquet").schema
    row = lambda i, day: (i, __import__("datetime").datetime(2024, 1, day), 1, "view", 1.0, "{}")
    for k, rows in enumerate(([row(0, 20)], [row(1, 21)], [row(2, 1), row(3, 21)])):
        spark.createDataFrame(rows, schema_).coalesce(1).write.mode("append").parquet(str(tmp_path / "late"))
        __import__("time").sleep(1.1)
    got = streams.collected(streams.tumbling(streams.events(spark, str(tmp_path / "late")), grid_of("EV")), "update")
    assert got.where("start_s < 1705000000").isEmpty() and got.agg(F.sum("load")).first()[0] >= 3


def test_registered_functions(spark):
    functions.register(spark)
    assert spark.sql("SELECT tile_of(5, 4, 10), cut_error(3, 10, 4, 2)").first()[:] == (2, 8)
    assert {m: functions.imbalance_of for m in ("a",)}["a"] is functions.imbalance_of
    assert metrics.phase_split({"push": 3.0, "solve": 1.0}) == {"push": 0.75, "solve": 0.25}
    df, took = metrics.timed(lambda: spark.range(10).toDF("id"))
    assert df.count() == 10 and took > 0


def test_equal_particles_stay_apart(spark):
    grid = Grid(8, 8, 1 << 12, 1 << 12)
    rows = [(1, 100, 200, 0, 0, 1, 0), (1, 100, 200, 0, 0, 1, 0), (None, 4095, 1, 0, 0, 1, 0), (None, 4095, 1, 0, 0, 1, 0)]
    df = spark.createDataFrame(rows, schema.PARTICLE)
    for elements in (mesh.quads(spark, 8, grid), mesh.hybrid(spark, 8, grid)):
        found = mesh.locate_elements(df, elements, grid).collect()
        assert len(found) == 4 and len({r["elem"] for r in found}) == 2
    assert mesh.locate_elements(df.limit(0), mesh.quads(spark, 8, grid), grid).count() == 0


@pytest.mark.parametrize(("n", "parts"), [(1, 4), (10, 4), (103, 8), (64, 8)])
def test_even_runs_are_those_of_ntile(spark, n, parts):
    from pyspark.sql import Window

    rows = spark.range(n).select(F.col("id").alias("elem"), F.pmod(F.col("id") * 37, F.lit(41)).alias("order"))
    want = rows.select("elem", (F.ntile(parts).over(Window.orderBy("order", "elem")) - 1).cast("long").alias("part"))
    got, total = mesh._even_runs(rows, parts, cells=7)
    assert total == n and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_pairs_need_no_global_synchronisation(spark):
    grid, df = grid_of("EV"), particles(spark, SF, "EV")
    first = lambda loads: partition.strips(loads, [4, 4])
    syncs = {name: run(df, Run(grid, 8, 3, "site", Every(1, policy), first))[1].orderBy(F.desc("t")).first()["syncs"] for name, policy in (("pairs", neighbours(None)), ("all", full))}
    assert syncs == {"pairs": 1, "all": 4}
    with pytest.raises(ValueError, match="too many"):
        run(df, Run(Grid(512, 512, 1 << 20, 1 << 20), 32))


def test_phases_of_a_step(spark):
    took = phases(two_stream(spark, 2000), Run(Grid(16, 16, 1 << 20, 1 << 20), 4, 1, "site", Every(1, tethered())))
    share = metrics.phase_split(took)
    assert set(share) == {"deposit", "field", "push", "rebalance", "move"} and min(took.values()) > 0 and sum(share.values()) == pytest.approx(1)


def test_long_diffusion_keeps_its_plan_short(spark):
    shared(spark)
    loads = spark.createDataFrame([(i, 100 * i) for i in range(6)], "pid long, load long")
    for history in (diffusion.diffuse(loads, diffusion.chain(spark, 6).select("a", "b").distinct(), steps=7), diffusion.exchange(loads, diffusion.chain(spark, 6), 7)):
        rows = diffusion.convergence(history).orderBy("t").collect()
        assert [r["t"] for r in rows] == list(range(8)) and all(r["total"] == pytest.approx(1500) for r in rows) and rows[-1]["spread"] < rows[0]["spread"]


def test_sources_without_a_number(spark):
    from tilebalance.sources.tables import document_items

    rows = spark.createDataFrame([(1, "t", "en", "web", 1), (2, "t", "en", "src12", 1), (3, "t", "en", None, 1)], "doc_id long, text string, lang string, source string, n_chars long")
    assert {r["pid_key"]: r["y"] for r in document_items(rows).collect()} == {1: 0, 2: 12, 3: None}
