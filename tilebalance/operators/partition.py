"""Cuts of the tile grid among owners: equal blocks, halving, proportional bisection, limited bisection, strips.

Cuts are exact in whole numbers. A cell with p owners gives p div 2 to its left side; with total W and
running cost S(q) the line q that minimises |S(q) * p - W * left| wins, then the one that moves an old
cut least, then the smallest. A cut leaves either side at least as many tiles as owners."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import CUT_TREE, SUBDOMAIN, TILE_OWNER
from .cost import LoadMap
from .grid import Grid, div, prefix_table, tiles


class TooManyProcessors(ValueError):
    """Some owner would have no tile."""


@dataclass(frozen=True)
class Leaf:
    pid: int
    x0: int
    x1: int
    y0: int
    y1: int
    height: int
    load: int

    @property
    def box(self) -> tuple[int, int, int, int]:
        return self.x0, self.x1, self.y0, self.y1


@dataclass(frozen=True)
class Node:
    node: int
    depth: int
    dim: str | None
    cut: int | None
    x0: int
    x1: int
    y0: int
    y1: int
    p_first: int
    p_count: int
    load: int

    @property
    def box(self) -> tuple[int, int, int, int]:
        return self.x0, self.x1, self.y0, self.y1

    @property
    def is_leaf(self) -> bool:
        return self.dim is None

    def sides(self) -> tuple[tuple[int, int, int, int], tuple[int, int, int, int]]:
        x0, x1, y0, y1 = self.box
        return ((x0, self.cut, y0, y1), (self.cut, x1, y0, y1)) if self.dim == "x" else ((x0, x1, y0, self.cut), (x0, x1, self.cut, y1))


@dataclass(frozen=True)
class Cut:
    """Rectangles of owners 0..P-1 over a grid of n by m tiles; those of a tree keep its nodes."""

    n: int
    m: int
    leaves: tuple[Leaf, ...]
    nodes: tuple[Node, ...] = ()
    rows: tuple[int, ...] = field(default=())
    first_dim: str = "x"

    @property
    def parts(self) -> int:
        return len(self.leaves)

    def owners(self) -> np.ndarray:
        out = np.full((self.n, self.m), -1, np.int64)
        for leaf in self.leaves:
            out[leaf.x0 : leaf.x1, leaf.y0 : leaf.y1] = leaf.pid
        return out

    def loads(self) -> list[int]:
        return [leaf.load for leaf in self.leaves]

    def reloaded(self, loads: LoadMap) -> Cut:
        """The same rectangles with the costs of another moment."""
        return replace(self, leaves=tuple(replace(x, load=loads.box(*x.box)) for x in self.leaves), nodes=tuple(replace(x, load=loads.box(*x.box)) for x in self.nodes))

    def frame(self, spark: SparkSession) -> DataFrame:
        """SUBDOMAIN."""
        return spark.createDataFrame([(x.pid, x.x0, x.x1, x.y0, x.y1, x.height, x.load) for x in self.leaves], SUBDOMAIN)

    def tree(self, spark: SparkSession) -> DataFrame:
        """CUT_TREE."""
        return spark.createDataFrame([(x.node, x.depth, x.dim, x.cut, *x.box, x.p_first, x.p_count, x.load, x.is_leaf) for x in self.nodes], CUT_TREE)

    def owner(self, ti: str | Column = "ti", tj: str | Column = "tj") -> Column:
        """The owner of a tile as one expression: a decision tree of comparisons, with no join and nothing to broadcast."""
        ti, tj = (F.col(c) if isinstance(c, str) else c for c in (ti, tj))

        def walk(leaves: list[Leaf]) -> Column:
            if len(leaves) == 1:
                return F.lit(leaves[0].pid).cast("long")
            for along, low, high in ((ti, "x0", "x1"), (tj, "y0", "y1")):
                starts = sorted({getattr(x, low) for x in leaves})[1:]
                whole = [s for s in starts if all(getattr(x, high) <= s or getattr(x, low) >= s for x in leaves)]
                if whole:
                    s = whole[len(whole) // 2]
                    return F.when(along < s, walk([x for x in leaves if getattr(x, high) <= s])).otherwise(walk([x for x in leaves if getattr(x, low) >= s]))
            raise ValueError("these rectangles cannot be told apart by straight cuts")

        return walk(list(self.leaves))


# equal blocks


def even_tiles(grid: Grid, columns: int, rows: int, loads: LoadMap | None = None) -> Cut:
    """columns x rows blocks of equal numbers of tiles, whatever they cost; sizes that do not divide are rounded down."""
    if columns > grid.n or rows > grid.m:
        raise TooManyProcessors(f"{columns} x {rows} blocks of {grid.n} x {grid.m} tiles")
    x = [grid.n * i // columns for i in range(columns + 1)]
    y = [grid.m * j // rows for j in range(rows + 1)]
    boxes = [(x[i], x[i + 1], y[j], y[j + 1]) for i in range(columns) for j in range(rows)]
    leaves = tuple(Leaf(k, *b, 0, loads.box(*b) if loads else 0) for k, b in enumerate(boxes))
    return Cut(grid.n, grid.m, leaves, rows=(rows,) * columns)


# recursive bisection on the gathered costs


def _by_prefix(s: np.ndarray, lo: int, p: int, left: int, allowed: np.ndarray, old: int | None) -> int:
    error = np.abs(s * p - s[-1] * left)
    q = lo + np.arange(len(s))
    moved = np.abs(q - old) if old is not None else np.zeros(len(s), np.int64)
    return int(min(np.flatnonzero(allowed), key=lambda i: (error[i], moved[i], q[i])) + lo)


def _by_dichotomy(s: np.ndarray, lo: int, p: int, left: int, allowed: np.ndarray, old: int | None) -> int:
    """Interval halving on the running cost, which never falls; plateaus are searched for their nearer end."""
    inside = np.flatnonzero(allowed)
    first, last = int(inside[0]), int(inside[-1])
    goal = s[-1] * left

    def least(value) -> int:  # smallest line in [first, last] whose running cost reaches value, last + 1 if none
        a, b = first, last + 1
        while a < b:
            c = (a + b) // 2
            a, b = (a, c) if s[c] >= value else (c + 1, b)
        return a

    above = least(-(-goal // p))
    ends = []
    for at in {min(above, last), max(first, min(above, last + 1) - 1)}:
        a = least(s[at])
        b = least(s[at] + 1) - 1  # the plateau of equal cost
        near = a if old is None else min(max(old - lo, a), b)
        ends += [a, near]
    return _by_prefix_few(s, lo, p, left, sorted(set(ends)), old)


def _by_prefix_few(s: np.ndarray, lo: int, p: int, left: int, few: list[int], old: int | None) -> int:
    return lo + min(few, key=lambda i: (abs(int(s[i]) * p - int(s[-1]) * left), abs(i + lo - old) if old is not None else 0, i))


def _room(box: tuple[int, int, int, int], dim: str, left: int, right: int) -> np.ndarray:
    """Lines of a dimension, its ends included, that leave either side enough tiles."""
    x0, x1, y0, y1 = box
    n, across = (x1 - x0, y1 - y0) if dim == "x" else (y1 - y0, x1 - x0)
    q = np.arange(n + 1)
    return (q * across >= left) & ((n - q) * across >= right) & (q > 0) & (q < n)


def _aspect(box: tuple[int, int, int, int]) -> float:
    a, b = box[1] - box[0], box[3] - box[2]
    return max(a, b) / min(a, b)


def _other(dim: str) -> str:
    return "y" if dim == "x" else "x"


def share_cut(loads: LoadMap, parts: int, first_dim: str = "x", rule: str = "alternate", search: str = "prefix", by: str = "cost", tolerance: float = 0.25, old: Cut | None = None, frozen: int = 0) -> Cut:
    """Proportional recursive bisection for any number of owners.

    rule: `alternate` dimensions; cut the `longest` side; or choose the split of owners too, for the best
    worst `aspect` among the splits that are off by at most `tolerance` of an owner's mean cost. search:
    `prefix` looks at every line, `dichotomy` halves intervals. by: `cost` or `extent`. old: a former tree, for
    ties, whose cuts above depth `frozen` are kept."""
    if parts < 1 or parts > loads.n * loads.m:
        raise TooManyProcessors(f"{parts} owners of {loads.n * loads.m} tiles")
    former = {x.node: x for x in old.nodes} if old else {}
    pick = {"prefix": _by_prefix, "dichotomy": _by_dichotomy}[search]
    nodes: list[Node] = []
    live = [Node(1, 0, first_dim, None, 0, loads.n, 0, loads.m, 0, parts, loads.total)]
    while live:
        below = []
        for cell in live:
            p = cell.p_count
            if p == 1:
                nodes.append(replace(cell, dim=None))
                continue
            was = former.get(cell.node)
            if was and not was.is_leaf and cell.depth < frozen:
                dim, cut, left = was.dim, was.cut, p // 2
            else:
                dim, cut, left = _choose(loads, cell, rule, pick, by, tolerance, was)
            done = replace(cell, dim=dim, cut=cut)
            nodes.append(done)
            for k, (box, first, count) in enumerate(zip(done.sides(), (cell.p_first, cell.p_first + left), (left, p - left), strict=True)):
                below.append(Node(2 * cell.node + k, cell.depth + 1, _other(dim), None, *box, first, count, loads.box(*box)))
        live = below
    nodes.sort(key=lambda x: x.node)
    return _of_tree(loads, nodes, first_dim)


def _choose(loads: LoadMap, cell: Node, rule: str, pick, by: str, tolerance: float, was: Node | None) -> tuple[str, int, int]:
    p, box = cell.p_count, cell.box
    scheduled = cell.dim
    if rule == "longest":
        a, b = box[1] - box[0], box[3] - box[2]
        scheduled = "x" if a > b else "y" if b > a else scheduled
    for dim in (scheduled, _other(scheduled)):
        low = box[0] if dim == "x" else box[2]
        s = loads.running(*box, dim)
        if by == "extent":
            allowed = _room(box, dim, p // 2, p - p // 2)
            s = np.arange(len(s)) * 1
        old = was.cut if was and was.dim == dim else None
        if rule == "aspect":
            found = []
            for left in range(1, p):
                allowed = _room(box, dim, left, p - left)
                if allowed.any():
                    cut = pick(s, low, p, left, allowed, old)
                    error = abs(int(s[cut - low]) * p - int(s[-1]) * left)
                    worst = max(map(_aspect, Node(0, 0, dim, cut, *box, 0, 0, 0).sides()))
                    found.append((error > tolerance * int(s[-1]), round(worst, 9) if error <= tolerance * int(s[-1]) else 0.0, error if error > tolerance * int(s[-1]) else 0, abs(2 * left - p), left, cut))
            if found:
                best = min(found)
                return dim, best[-1], best[-2]
            continue
        allowed = _room(box, dim, p // 2, p - p // 2)
        if allowed.any():
            return dim, pick(s, low, p, p // 2, allowed, old), p // 2
    raise TooManyProcessors(f"{p} owners of the tiles {box}")


def _of_tree(loads: LoadMap, nodes: list[Node], first_dim: str) -> Cut:
    ends = sorted((x for x in nodes if x.is_leaf), key=lambda x: x.p_first)
    return Cut(loads.n, loads.m, tuple(Leaf(x.p_first, *x.box, x.depth, x.load) for x in ends), tuple(nodes), first_dim=first_dim)


def halving(loads: LoadMap, parts: int, first_dim: str = "x", by: str = "cost") -> Cut:
    """Bisection into equal halves for a power of two of owners; by `extent`, at the middle line."""
    if parts < 1 or parts & (parts - 1):
        raise ValueError(f"{parts} is no power of two")
    return share_cut(loads, parts, first_dim, by=by)


# limited bisection


def _ancestors(node: int) -> list[int]:
    return [node >> k for k in range(1, node.bit_length())]


def movable(cut: Cut, level: int | None) -> set[int]:
    """Cut nodes at a depth, and shallower ones whose both sides are leaves; none of them is above another."""
    inner = {x.node: x for x in cut.nodes if not x.is_leaf}
    deepest = max((x.depth for x in inner.values()), default=0)
    level = deepest if level is None else level
    return {k for k, x in inner.items() if x.depth == level or x.depth < level and 2 * k not in inner and 2 * k + 1 not in inner}


def tethered_cut(old: Cut, loads: LoadMap, level: int | None = None, frontier: str = "one") -> Cut:
    """The old tree with only some cuts moved, so that no more than one border of any owner moves.

    frontier `one`: cuts at a depth (the deepest by default) move, strictly between the cuts of their
    dimension below them. `subtree`: cuts above the depth stay, all from it down are made anew."""
    if frontier == "subtree":
        depth = max((x.depth for x in old.nodes if not x.is_leaf), default=0) if level is None else level
        return share_cut(loads, old.parts, old.first_dim, old=old, frozen=depth)
    nodes = {x.node: x for x in old.nodes}
    for k in sorted(movable(old, level)):
        x = nodes[k]
        below = [y for j, y in nodes.items() if not y.is_leaf and y.dim == x.dim and k in _ancestors(j)]
        left, right = [y.cut for y in below if y.cut < x.cut], [y.cut for y in below if y.cut > x.cut]
        low = x.x0 if x.dim == "x" else x.y0
        allowed = _room(x.box, x.dim, x.p_count // 2, x.p_count - x.p_count // 2)
        q = low + np.arange(len(allowed))
        allowed &= (q > max(left, default=low)) & (q < min(right, default=q[-1]))
        allowed |= q == x.cut
        new = _by_prefix(loads.running(*x.box, x.dim), low, x.p_count, x.p_count // 2, allowed, x.cut)
        ends = ("x0", "x1") if x.dim == "x" else ("y0", "y1")
        for j, y in list(nodes.items()):
            if k in _ancestors(j):
                nodes[j] = replace(y, **{e: new for e in ends if getattr(y, e) == x.cut})
        nodes[k] = replace(x, cut=new)
    return _of_tree(loads, [replace(x, load=loads.box(*x.box)) for x in sorted(nodes.values(), key=lambda x: x.node)], old.first_dim)


def imbalance(loads: list[int]) -> float:
    """Greatest load by the mean; 1 when nothing is loaded."""
    return max(loads) * len(loads) / sum(loads) if sum(loads) else 1.0


def tethered_or_full(old: Cut, loads: LoadMap, level: int | None = None, theta: float = 1.25) -> tuple[Cut, bool]:
    """The limited cut, or a cut from scratch where its imbalance exceeds theta; and whether it came to that."""
    cut = tethered_cut(old, loads, level)
    return (share_cut(loads, old.parts, old.first_dim), True) if imbalance(cut.loads()) > theta else (cut, False)


# strips


def _borders(s: np.ndarray, shares: list[int]) -> list[int]:
    """Lines that cut a running cost in proportion to shares, each side getting a line at least."""
    total, whole, n, k = int(s[-1]), sum(shares), len(s) - 1, len(shares)
    if k > n:
        raise TooManyProcessors(f"{k} strips of {n} lines")
    out, upto = [0], 0
    for i, share in enumerate(shares[:-1], 1):
        upto += share
        best = int(np.argmin(np.abs(s * whole - total * upto)))
        out.append(min(max(best, out[-1] + 1), n - (k - i)))
    return [*out, n]


def strips(loads: LoadMap, rows: list[int], first_dim: str = "x") -> Cut:
    """Columns cut by cost in proportion to their numbers of owners, then each column into its owners, on its own."""
    wide = loads.n if first_dim == "x" else loads.m
    across = _borders(loads.running(0, loads.n, 0, loads.m, first_dim), list(rows))
    assert across[-1] == wide
    leaves = []
    for c, count in enumerate(rows):
        a, b = across[c], across[c + 1]
        whole = (a, b, 0, loads.m) if first_dim == "x" else (0, loads.n, a, b)
        along = _borders(loads.running(*whole, _other(first_dim)), [1] * count)
        for r in range(count):
            box = (a, b, along[r], along[r + 1]) if first_dim == "x" else (along[r], along[r + 1], a, b)
            leaves.append(Leaf(len(leaves), *box, 2, loads.box(*box)))
    return Cut(loads.n, loads.m, tuple(leaves), rows=tuple(rows), first_dim=first_dim)


# tables


def expand(subdomains: DataFrame) -> DataFrame:
    """TILE_OWNER of SUBDOMAIN."""
    side = lambda a, b: F.sequence(F.col(a), F.col(b) - 1)
    return subdomains.select("pid", F.explode(side("x0", "x1")).alias("ti"), "y0", "y1").select("ti", F.explode(side("y0", "y1")).alias("tj"), "pid")


def collapse(tile_owner: DataFrame) -> DataFrame:
    """The rectangle of each owner in TILE_OWNER, and whether its tiles fill it."""
    x0, x1, y0, y1 = F.min("ti"), F.max("ti") + 1, F.min("tj"), F.max("tj") + 1
    return tile_owner.groupBy("pid").agg(x0.alias("x0"), x1.alias("x1"), y0.alias("y0"), y1.alias("y1"), (F.count("*") == (x1 - x0) * (y1 - y0)).alias("full"))


def even_owner(spark: SparkSession, grid: Grid, columns: int, rows: int) -> DataFrame:
    """TILE_OWNER of equal blocks for grids of any size, as a projection of the tiles."""
    block = lambda t, k, n: div((F.col(t) + 1) * k - 1, n)
    return tiles(spark, grid).select("ti", "tj", (block("ti", columns, grid.n) * rows + block("tj", rows, grid.m)).alias("pid"))


assert TILE_OWNER.fieldNames() == ["ti", "tj", "pid"]


# the level-wise engine, for grids that no driver should hold


def share_cut_levels(tile_loads: DataFrame, grid: Grid, parts: int, first_dim: str = "x", value: str = "cost", store=None) -> DataFrame:
    """SUBDOMAIN by the same rule as share_cut, one round of joins for each level; no tile comes to the driver.

    Candidate lines of all live cells look their running costs up in the prefix table; the least error per cell wins by
    a minimum that is combined before its shuffle. store: cuts the lineage of the list of cells, which each round reads
    three times."""
    if parts > grid.tiles:
        raise TooManyProcessors(f"{parts} owners of {grid.tiles} tiles")
    spark = tile_loads.sparkSession
    store = store or (lambda df: df.checkpoint())
    prefix = store(prefix_table(tile_loads, grid, value))
    c = lambda name: F.col(name)
    at = lambda i, j, to: prefix.select(c("i").alias(i), c("j").alias(j), c("s").alias(to))
    total = prefix.where((c("i") == grid.n) & (c("j") == grid.m)).select("s")
    cells = total.select(*[F.lit(v).cast("long").alias(k) for k, v in (("node", 1), ("depth", 0), ("x0", 0), ("x1", grid.n), ("y0", 0), ("y1", grid.m), ("p_first", 0), ("p_count", parts))], F.lit(first_dim).alias("dim"), c("s").alias("load"))
    done = []
    for _ in range(max(1, (parts - 1).bit_length())):
        live = cells.where("p_count > 1")
        left = div(c("p_count"), 2)
        lines = []
        for d, a, b, lo, hi in (("x", "x0", "x1", "y0", "y1"), ("y", "y0", "y1", "x0", "x1")):
            q = live.where(c(b) - c(a) > 1).select("*", F.explode(F.sequence(c(a) + 1, c(b) - 1)).alias("q"))
            across = c(hi) - c(lo)
            q = q.where(((c("q") - c(a)) * across >= left) & ((c(b) - c("q")) * across >= c("p_count") - left))
            keys = (("q", hi), ("q", lo), (a, hi), (a, lo)) if d == "x" else ((hi, "q"), (lo, "q"), (hi, a), (lo, a))
            for k, (i, j) in enumerate(keys):
                q = q.join(at(i, j, f"s{k}"), [i, j])
            lines.append(q.select("node", F.lit(d).alias("d"), "q", (c("s0") - c("s1") - c("s2") + c("s3")).alias("left_load")))
        found = live.join(lines[0].union(lines[1]), "node")
        error = F.abs(c("left_load") * c("p_count") - c("load") * left)
        best = found.groupBy("node").agg(F.min(F.struct((c("d") != c("dim")).alias("off"), error.alias("error"), "q", "d", "left_load")).alias("best"))
        cut = live.join(best, "node", "left").select("*", "best.q", "best.d", "best.left_load", left.alias("pl"))
        cut = cut.withColumn("q", F.coalesce("q", F.raise_error(F.lit("an owner would have no tile")).cast("long")))
        side = lambda k: F.struct(
            (c("node") * 2 + k).alias("node"), (c("depth") + 1).alias("depth"),
            F.when(c("d") == "x", c("q") if k else c("x0")).otherwise(c("x0")).alias("x0"), F.when(c("d") == "x", c("x1") if k else c("q")).otherwise(c("x1")).alias("x1"),
            F.when(c("d") == "y", c("q") if k else c("y0")).otherwise(c("y0")).alias("y0"), F.when(c("d") == "y", c("y1") if k else c("q")).otherwise(c("y1")).alias("y1"),
            (c("p_first") + (c("pl") if k else 0)).alias("p_first"), (c("p_count") - c("pl") if k else c("pl")).alias("p_count"),
            F.when(c("d") == "x", "y").otherwise("x").alias("dim"), (c("load") - c("left_load") if k else c("left_load")).alias("load"),
        )
        done.append(cells.where("p_count = 1"))
        cells = store(cut.select(F.explode(F.array(side(0), side(1))).alias("side")).select("side.*"))
    done.append(cells)
    every = done[0]
    for more in done[1:]:
        every = every.union(more)
    return every.select(c("p_first").alias("pid"), "x0", "x1", "y0", "y1", c("depth").alias("height"), "load")
