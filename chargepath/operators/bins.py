"""Uniform bins over the plane: index, linked lists, rings, radius and nearest queries."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from math import ceil, floor, log2, pi, sqrt

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from chargepath.operators.search import cut


@dataclass(frozen=True)
class BinGrid:
    """Square cells; a bin's number is ni * j + i. World bounds by default."""

    cell: float
    xmin: float = -180.0
    ymin: float = -90.0
    xmax: float = 180.0
    ymax: float = 90.0

    @property
    def ni(self) -> int:
        return int((self.xmax - self.xmin) // self.cell) + 1

    @property
    def nj(self) -> int:
        return int((self.ymax - self.ymin) // self.cell) + 1

    def i(self, x="x"):
        return F.floor((F.col(x) - self.xmin) / self.cell)

    def j(self, y="y"):
        return F.floor((F.col(y) - self.ymin) / self.cell)

    def bin(self, x="x", y="y"):
        return self.j(y) * self.ni + self.i(x)

    def bin_at(self, x: float, y: float) -> int:
        return floor((y - self.ymin) / self.cell) * self.ni + floor((x - self.xmin) / self.cell)

    def block(self, cell: int, k: int) -> list[int]:
        """The cells within k of a cell, clipped to the grid."""
        i, j = cell % self.ni, cell // self.ni
        return [b * self.ni + a for b in range(max(0, j - k), min(self.nj, j + k + 1)) for a in range(max(0, i - k), min(self.ni, i + k + 1))]


def cell_from_km(km: float, latitude: float = 0.0) -> float:
    """Degrees of longitude that km are at a latitude."""
    from math import cos, radians

    return km / (111.195 * max(0.01, cos(radians(latitude))))


def with_bin(items: DataFrame, grid: BinGrid) -> DataFrame:
    return items.withColumn("bin", grid.bin())


def around(rows: DataFrame, grid: BinGrid, k: int, ring_only: bool = False) -> DataFrame:
    """rows(bin, ...) -> each bin within k cells of the row's (or exactly k), clipped to the grid, as near."""
    i, j = F.col("bin") % grid.ni, F.floor(F.col("bin") / grid.ni)
    steps = [(a, b) for a in range(-k, k + 1) for b in range(-k, k + 1) if not ring_only or max(abs(a), abs(b)) == k]
    near = F.explode(F.array(*[F.struct((i + a).alias("i"), (j + b).alias("j")) for a, b in steps]))
    out = rows.withColumn("_c", near).where(f"_c.i >= 0 AND _c.i < {grid.ni} AND _c.j >= 0 AND _c.j < {grid.nj}")
    return out.withColumn("near", F.col("_c.j") * grid.ni + F.col("_c.i")).drop("_c")


def links(items: DataFrame, key: str = "station") -> DataFrame:
    """items(bin) -> item, bin, prev, next: each bin's items as a doubly linked list, newest first."""
    order = Window.partitionBy("bin").orderBy(F.col(key).desc())
    return items.select(F.col(key).alias("item"), "bin", F.lag(key).over(order).alias("prev"), F.lead(key).over(order).alias("next"))


def heads(items: DataFrame, key: str = "station") -> DataFrame:
    """bin, head, items: the entry of each bin's list."""
    return items.groupBy("bin").agg(F.max(key).alias("head"), F.count("*").alias("items"))


def within(points: DataFrame, items: DataFrame, grid: BinGrid, radius: float) -> DataFrame:
    """points(point, x, y) x items(item, x, y) -> point, item, d2 within radius, by an equi-join of bins."""
    p, q = points.select("point", F.col("x").alias("px"), F.col("y").alias("py"), *cells(grid)), items.select("item", "x", "y", *cells(grid))
    k = int(-(-radius // grid.cell))
    if items.count() <= points.count():  # the smaller table is the one repeated in the cells around
        q = spread_out(q, k)
    else:
        p = spread_out(p, k)
    d2 = (F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py"))
    return p.join(q.hint("merge"), ["i", "j"]).select("point", "item", d2.alias("d2")).where(F.col("d2") <= radius * radius)


def cells(grid: BinGrid) -> list:
    return [grid.i().alias("i"), grid.j().alias("j")]


def spread_out(rows: DataFrame, k: int) -> DataFrame:
    """rows(i, j) in each cell within k of their own. Spark's estimate of the size does not know of it, so joins with it must name how."""
    steps = F.array(*[F.lit(a) for a in range(-k, k + 1)])
    out = rows.withColumn("_a", F.explode(steps)).withColumn("_b", F.explode(steps))
    return out.withColumns({"i": F.col("i") + F.col("_a"), "j": F.col("j") + F.col("_b")}).drop("_a", "_b")


def within_scan(points: DataFrame, items: DataFrame, radius: float) -> DataFrame:
    """The same without an index; a baseline for small inputs, every pair is looked at."""
    p = points.select("point", F.col("x").alias("px"), F.col("y").alias("py"))
    d2 = (F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py"))
    return p.crossJoin(items.select("item", "x", "y")).select("point", "item", d2.alias("d2")).where(F.col("d2") <= radius * radius)


def nearest(points: DataFrame, items: DataFrame, grid: BinGrid, n: int = 1) -> DataFrame:
    """The n nearest items of each point (by distance, then item), growing rings
    until the n-th is no further than the rings reach.

    The first block of rings is as wide as the items' density asks for, so that
    most points need one round; each round is cut, and only points without
    enough items go on.
    """
    last = max(grid.ni, grid.nj)
    # Of items at one place only the first n can be among the nearest.
    items = cut(items.withColumn("_nth", F.row_number().over(Window.partitionBy("x", "y").orderBy("item"))).where(F.col("_nth") <= n).select("item", "x", "y"))
    held = items.groupBy(*cells(grid)).agg(F.count("*").alias("c")).agg((F.sum(F.col("c") * F.col("c")) / F.sum("c")).alias("d")).first()
    density = held.d or 0.0  # of an item's own cell: where items crowd, a cell of mean density would hold far too many
    k = min(last, max(1, ceil(sqrt(2 * n / (pi * density))))) if density else last
    left, parts = points, []
    while True:
        reach = k * grid.cell
        found = within(left, items, grid, reach if k < last else reach * 2)
        window = Window.partitionBy("point")
        found = found.withColumns({"rank": F.row_number().over(window.orderBy("d2", "item")), "_n": F.count("*").over(window)})
        enough = F.col("_n") >= n if k < last else F.lit(True)
        parts.append(cut(found.where((F.col("rank") <= n) & enough).drop("_n")))
        if k >= last:
            break
        left = cut(left.join(parts[-1].select("point").distinct(), "point", "left_anti"))
        if left.isEmpty():
            break
        k = min(last, 2 * k)
    return reduce(DataFrame.unionByName, parts)


def bin_stats(points: DataFrame, items: DataFrame, grid: BinGrid, radius: float) -> DataFrame:
    """One row: items, integers of the lists, heads, bins visited, items looked at and returned by a radius search."""
    k = int(-(-radius // grid.cell))
    near = around(with_bin(points.select("point", "x", "y"), grid), grid, k)
    held = with_bin(items, grid)
    pairs = points.select("point", F.col("x").alias("px"), F.col("y").alias("py"), *cells(grid)).join(spread_out(items.select("item", "x", "y", *cells(grid)), k).hint("merge"), ["i", "j"])
    d2 = (F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py"))
    size = held.agg(F.count("*").alias("items"), (3 * F.count("*")).alias("list_integers"), F.count_distinct("bin").alias("heads"))
    scans = pairs.agg(F.count("*").alias("scanned"), F.coalesce(F.sum((d2 <= radius * radius).cast("long")), F.lit(0)).alias("returned"))
    return size.crossJoin(near.agg(F.count("*").alias("bins_visited"))).crossJoin(scans)  # three rows of one


def quad_keys(items: DataFrame, levels: int, box: tuple[float, float, float, float]) -> DataFrame:
    """items + quad: the path of a quadtree of fixed depth, a digit of 0..3 a level; the tree baseline."""
    x0, y0, x1, y1 = box
    n = 1 << levels
    i = F.least(F.floor((F.col("x") - x0) / (x1 - x0) * n), F.lit(n - 1)).cast("long")
    j = F.least(F.floor((F.col("y") - y0) / (y1 - y0) * n), F.lit(n - 1)).cast("long")
    digits = [F.shiftright(i, k).bitwiseAND(F.lit(1)) + 2 * F.shiftright(j, k).bitwiseAND(F.lit(1)) for k in range(levels - 1, -1, -1)]
    return items.withColumn("quad", F.concat(*[d.cast("string") for d in digits]))


def quad_tree(items: DataFrame, levels: int, box: tuple[float, float, float, float], capacity: int) -> DataFrame:
    """leaf, items: the shallowest quads that hold at most capacity items."""
    keyed = quad_keys(items, levels, box)
    prefixes = keyed.select(F.explode(F.transform(F.sequence(F.lit(1), F.lit(levels)), lambda k: F.substring("quad", F.lit(1), k))).alias("leaf"))
    counts = prefixes.groupBy("leaf").agg(F.count("*").alias("items"))
    parent = counts.select(F.col("leaf").alias("up"), F.col("items").alias("above"))
    joined = counts.join(parent, F.expr("substring(leaf, 1, length(leaf) - 1) = up"), "left")
    small = (F.col("items") <= capacity) | (F.length("leaf") == levels)
    return joined.where(small & (F.coalesce("above", F.lit(capacity + 1)) > capacity)).select("leaf", "items")


def within_quadtree(points: DataFrame, items: DataFrame, levels: int, box: tuple[float, float, float, float], capacity: int, radius: float) -> DataFrame:
    """points x items -> point, item, d2 within radius, through the leaves of the tree.

    A circle touches at most nine quads of the deepest level whose quads are as
    wide as the radius; leaves above that level are found by the quads' own
    prefixes, leaves below it by the leaf's.
    """
    x0, y0, x1, y1 = box
    level = max(1, min(levels, floor(-log2(radius / min(x1 - x0, y1 - y0))) if radius > 0 else levels))
    n = 1 << level
    leaves = quad_tree(items, levels, box, capacity).select("leaf")
    keyed = quad_keys(items, levels, box)
    prefixes = keyed.select("item", "x", "y", F.explode(F.transform(F.sequence(F.lit(1), F.lit(levels)), lambda k: F.substring("quad", F.lit(1), k))).alias("leaf"))
    held = prefixes.join(leaves, "leaf").withColumn("near", F.substring("leaf", 1, level))
    wide, high = (x1 - x0) / n, (y1 - y0) / n
    cell = lambda c, start, size, k: F.greatest(F.lit(0), F.least(F.floor((F.col(c) + k * radius - start) / size), F.lit(n - 1))).cast("long")
    own = points.select("point", F.col("x").alias("px"), F.col("y").alias("py"))
    i = F.explode(F.sequence(cell("px", x0, wide, -1), cell("px", x0, wide, 1)))
    j = F.explode(F.sequence(cell("py", y0, high, -1), cell("py", y0, high, 1)))
    quads = own.withColumn("i", i).withColumn("j", j)
    digits = [F.shiftright("i", k).bitwiseAND(F.lit(1)) + 2 * F.shiftright("j", k).bitwiseAND(F.lit(1)) for k in range(level - 1, -1, -1)]
    quads = quads.withColumn("quad", F.concat(*[d.cast("string") for d in digits]))
    above = quads.select("point", "px", "py", F.explode(F.transform(F.sequence(F.lit(1), F.lit(level)), lambda k: F.substring("quad", F.lit(1), k))).alias("near")).distinct()
    d2 = (F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py"))
    return above.join(held, "near").select("point", "item", d2.alias("d2")).where(F.col("d2") <= radius * radius)

