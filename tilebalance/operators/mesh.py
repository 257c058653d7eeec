"""Meshes of quads, triangles and both; barycentres, element location and topology."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .grid import Grid, div, tile_x, tile_y


def _vertex(i: Column, j: Column, k: int, lx: int, ly: int, jitter: bool) -> Column:
    """A vertex of the k by k lattice; inner ones are moved by a rule of their place, by less than a quarter of a side."""
    x, y = div(i * lx, k), div(j * ly, k)
    if not jitter:
        return F.struct(x.alias("x"), y.alias("y"))
    inner = (i > 0) & (i < k) & (j > 0) & (j < k)
    qx, qy = max(1, lx // k // 4), max(1, ly // k // 4)
    dx, dy = F.pmod(i * 7_919 + j * 104_729, F.lit(2 * qx - 1)) - (qx - 1), F.pmod(i * 15_485_863 + j * 32_452_843, F.lit(2 * qy - 1)) - (qy - 1)
    return F.struct((x + F.when(inner, dx).otherwise(0)).alias("x"), (y + F.when(inner, dy).otherwise(0)).alias("y"))


def _elements(spark: SparkSession, k: int, grid: Grid, kind: Column, jitter: bool) -> DataFrame:
    i, j = div(F.col("id"), k), F.pmod("id", F.lit(k))
    v = lambda a, b: _vertex(i + a, j + b, k, grid.lx, grid.ly, jitter)
    quad = F.array(v(0, 0), v(1, 0), v(1, 1), v(0, 1))
    low, high = F.array(v(0, 0), v(1, 0), v(1, 1)), F.array(v(0, 0), v(1, 1), v(0, 1))
    one = F.struct(F.lit("quad").alias("kind"), quad.alias("verts"), F.lit(0).alias("part"))
    two = F.array(F.struct(F.lit("tri").alias("kind"), low.alias("verts"), F.lit(0).alias("part")), F.struct(F.lit("tri").alias("kind"), high.alias("verts"), F.lit(1).alias("part")))
    made = spark.range(k * k).select((F.col("id") * 2).alias("base"), F.explode(F.when(kind, F.array(one)).otherwise(two)).alias("e"))
    return with_barycentre(made.select((F.col("base") + F.col("e.part")).alias("elem"), "e.kind", "e.verts"))


def quads(spark: SparkSession, k: int, grid: Grid) -> DataFrame:
    """ELEMENT of k * k quads; their numbers are even, so that meshes of one k share them."""
    return _elements(spark, k, grid, F.lit(True), False)


def triangles(spark: SparkSession, k: int, grid: Grid) -> DataFrame:
    """ELEMENT of 2 * k * k triangles over a lattice with moved inner vertices."""
    return _elements(spark, k, grid, F.lit(False), True)


def hybrid(spark: SparkSession, k: int, grid: Grid) -> DataFrame:
    """ELEMENT of quads in the left half and triangles in the right one; vertices are not moved."""
    return _elements(spark, k, grid, div(F.col("id"), k) < k // 2, False)


def with_barycentre(elements: DataFrame) -> DataFrame:
    """Elements with the whole part of the mean of their vertices."""
    mean = lambda c: div(F.aggregate("verts", F.lit(0).cast("long"), lambda s, v: s + v[c]), F.size("verts").cast("long"))
    return elements.withColumns({"bx": mean("x"), "by": mean("y")})


def part_elements(part: DataFrame) -> DataFrame:
    """Scattered elements of the part table, given by their barycentres: size by price."""
    price = F.pmod(F.round(F.col("p_retailprice") * 100).cast("long") - 90_000, F.lit(16_384))
    return part.select(F.col("p_partkey").alias("elem"), F.col("p_size").cast("long").alias("bx"), price.alias("by"))


def assign_tiles(elements: DataFrame, grid: Grid) -> DataFrame:
    """Elements with the tile of their barycentre."""
    return elements.withColumns({"ti": tile_x(grid, "bx"), "tj": tile_y(grid, "by")})


def locate_quads(particles: DataFrame, k: int, grid: Grid) -> DataFrame:
    """Particles with the quad they are in, by arithmetic alone."""
    i, j = div(F.col("x") * k, grid.lx), div(F.col("y") * k, grid.ly)
    return particles.withColumn("elem", (i * k + j) * 2)


def locate_elements(particles: DataFrame, elements: DataFrame, grid: Grid) -> DataFrame:
    """Particles with the element they are in, of any convex mesh; one on a shared edge gets the lowest number, and
    one outside of the mesh is left out. Equal particles stay apart.

    Every element is sent to the tiles that its bounding box meets; a tile's elements are one row, which its particles
    are joined with, so that particles are shuffled once at most. Sides of the polygon are tested by orientation."""
    side = lambda c, f: f(F.transform("verts", lambda v: v[c]))
    clip = lambda z, size: F.least(z, F.lit(size - 1))
    span = lambda c, n, size: F.explode(F.sequence(div(clip(side(c, F.array_min), size) * n, size), div(clip(side(c, F.array_max), size) * n, size)))
    cover = elements.select("elem", "verts", span("x", grid.n, grid.lx).alias("ti")).select("elem", "verts", "ti", span("y", grid.m, grid.ly).alias("tj"))

    def turn(v: Column, i: Column) -> Column:
        a, b = F.get(v, i), F.get(v, F.pmod(i + 1, F.size(v)))
        return (b["x"] - a["x"]).cast("double") * (F.col("y") - a["y"]) - (b["y"] - a["y"]).cast("double") * (F.col("x") - a["x"])

    inside = lambda e: F.forall(F.sequence(F.lit(0), F.size(e["verts"]) - 1), lambda i: turn(e["verts"], i) >= 0)
    near = cover.groupBy("ti", "tj").agg(F.collect_list(F.struct("elem", "verts")).alias("near"))
    located = particles.withColumns({"ti": tile_x(grid), "tj": tile_y(grid)}).join(near, ["ti", "tj"])
    elem = F.array_min(F.transform(F.filter("near", inside), lambda e: e["elem"]))
    return located.select(*[F.col(c) for c in particles.columns if c != "elem"], elem.alias("elem")).where("elem is not null")


def incidence(elements: DataFrame) -> DataFrame:
    """(elem, edge, sign): the edges around each element, named by their ends in a fixed order, with the direction of travel."""
    n = F.size("verts")
    ends = F.transform("verts", lambda v, i: F.struct(v.alias("a"), F.get("verts", F.pmod(i + 1, n)).alias("b")))
    rows = elements.select("elem", F.explode(ends).alias("s"))
    return rows.select("elem", F.xxhash64(F.least("s.a", "s.b"), F.greatest("s.a", "s.b")).alias("edge"), F.when(F.col("s.a") < F.col("s.b"), 1).otherwise(-1).alias("sign"))


def adjacency(elements: DataFrame) -> DataFrame:
    """(a, b) of elements that share an edge, both ways."""
    i = incidence(elements)
    p, q = i.select(F.col("elem").alias("a"), "edge"), i.select(F.col("elem").alias("b"), "edge")
    return p.join(q, "edge").where("a <> b").select("a", "b").distinct()


def counts(elements: DataFrame) -> DataFrame:
    """(elements, edges, vertices) of a mesh with straight, not periodic, borders."""
    n = elements.agg(F.count("*").alias("elements"))
    e = incidence(elements).agg(F.count_distinct("edge").alias("edges"))
    v = elements.select(F.explode("verts").alias("v")).agg(F.count_distinct("v").alias("vertices"))
    return n.join(e).join(v)


def _even_runs(ordered: DataFrame, parts: int, cells: int = 1 << 12) -> tuple[DataFrame, int]:
    """(elem, part) in runs along `order` that differ by one at most, and the number of elements. Elements are ranked
    in cells of the order, each behind the counts of the cells before it, so no task ranks them all."""
    low, high = ordered.agg(F.min("order"), F.max("order")).first()
    if low is None:
        return ordered.select("elem", F.lit(0).cast("long").alias("part")), 0
    cell = F.call_function("div", F.col("order") - low, F.lit(max(1, -(-(high - low + 1) // cells))))
    placed = ordered.select("elem", "order", cell.alias("cell"))
    counts = {r["cell"]: r["count"] for r in placed.groupBy("cell").count().collect()}  # a row for each cell at most
    total, before, rows = sum(counts.values()), 0, []
    for c in sorted(counts):
        rows.append((c, before))
        before += counts[c]
    starts = F.broadcast(ordered.sparkSession.createDataFrame(rows, "cell long, before long"))
    rank = F.col("before") + F.row_number().over(Window.partitionBy("cell").orderBy("order", "elem")) - 1
    # the first runs hold one element more, as many as the rest of the division
    size, more = divmod(total, parts)
    long = more * (size + 1)
    part = F.when(F.col("rank") < long, div(F.col("rank"), size + 1)).otherwise(F.lit(more) + div(F.col("rank") - long, max(1, size)))
    return placed.join(starts, "cell").select("elem", rank.alias("rank")).select("elem", part.cast("long").alias("part")), total


def graph_cut(elements: DataFrame, parts: int, rounds: int = 8, slack: float = 0.05, store=None) -> DataFrame:
    """(elem, part): the off-line baseline. Elements start in equal runs along a space-filling order and pass messages
    to their neighbours; each round those with more neighbours in another part go there, while its size stays within the slack.

    As costly as the name suggests: each round joins the whole adjacency."""
    from ..functions.exprs import interleave
    from .lineage import stored

    store = store or stored
    links = store(adjacency(elements))
    now, total = _even_runs(elements.select("elem", interleave(F.col("bx"), F.col("by")).alias("order")), parts)
    now = store(now)
    most = int((1 + slack) * total / parts) + 1
    for r in range(rounds):
        near = links.join(now.select(F.col("elem").alias("b"), F.col("part").alias("to")), "b").groupBy(F.col("a").alias("elem"), "to").agg(F.count("*").alias("n"))
        own = near.join(now, "elem")
        best = own.groupBy("elem").agg(F.max(F.struct("n", -F.col("to"), "to")).alias("best"), F.coalesce(F.max(F.when(F.col("to") == F.col("part"), F.col("n"))), F.lit(0)).alias("here"), F.first("part").alias("part"))
        # parts take turns by parity, so that two do not swap borders for ever
        wish = best.where((F.col("best.n") > F.col("here")) & (F.pmod(F.col("best.to") + F.col("part"), F.lit(2)) == r % 2)).select("elem", F.col("best.to").alias("to"), (F.col("best.n") - F.col("here")).alias("gain"))
        sizes = now.groupBy(F.col("part").alias("to")).agg(F.count("*").alias("size"))
        room = F.lit(most) - F.coalesce("size", F.lit(0))
        go = wish.join(F.broadcast(sizes), "to", "left").withColumn("rank", F.row_number().over(Window.partitionBy("to").orderBy(F.desc("gain"), "elem"))).where(F.col("rank") <= room).select("elem", "to")
        now = store(now.join(go, "elem", "left").select("elem", F.coalesce("to", "part").alias("part")))
    return now


def edge_cut(parts: DataFrame, links: DataFrame) -> DataFrame:
    """Adjacent elements in different parts, each pair once."""
    a, b = parts.select(F.col("elem").alias("a"), F.col("part").alias("p")), parts.select(F.col("elem").alias("b"), F.col("part").alias("q"))
    return links.where("a < b").join(a, "a").join(b, "b").agg(F.count("*").alias("pairs"), F.count_if(F.col("p") != F.col("q")).alias("cut"))
