"""What the driver, the disk and the rounds take on larger tables, seen on the smallest ones."""

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.operators import bins, planner, search
from chargepath.plans import queries
from chargepath.sources import fixtures

SMALL, LESS_SMALL = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def test_networks_reach_the_driver_packed(spark, monkeypatch):
    edges, nodes = fixtures.edges(spark, SMALL), fixtures.nodes(spark, SMALL)
    want = sorted(map(tuple, edges.collect()))

    def refused(self):
        raise AssertionError("a table of edges on the driver")

    monkeypatch.setattr(DataFrame, "toPandas", refused)
    net = search.load(edges, nodes).value
    assert sorted((int(v), t, w) for v in net.ids for t, w in net.out(int(v))) == want
    assert net.dst.dtype == net.weight.dtype == np.int32 and isinstance(net._at, search.Run)
    assert net.spot(17) == (2.0, 1.0) and net.spot(150) is None and net.out(-1) == ()
    wide = spark.createDataFrame([(1 << 40, 5, 2), (5, 7, 1)], "src long, dst long, weight long")
    assert list(search.load(wide).value.out(1 << 40)) == [(5, 2)]
    assert search.load(wide.limit(0)).value.out(5) == ()


def test_joins_of_cells_are_not_broadcast(spark):
    """Spark takes rows repeated in the cells around for as few as they were before."""
    _, points, items = queries._points(spark, SMALL)
    grid = bins.BinGrid(4.0, 0.0, 0.0, 15.0, 11.0)
    plan = bins.within(points, items, grid, 6.0)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan


def test_points_outside_the_grid(spark):
    points = spark.createDataFrame([(1, -3.0, -3.0), (2, 25.0, 4.0)], "point long, x double, y double")
    items = spark.createDataFrame([(7, 0.0, 0.0), (8, 19.0, 4.0), (9, 19.0, 4.0)], "item long, x double, y double")
    got = bins.within(points, items, bins.BinGrid(4.0, 0.0, 0.0, 20.0, 20.0), 6.0).collect()
    assert sorted(map(tuple, got)) == [(1, 7, 18.0), (2, 8, 36.0), (2, 9, 36.0)]


def test_runs_of_a_cell_share_their_edges(spark):
    """An edge is shipped to a few cells, not to every run near it."""
    edges, nodes = fixtures.edges(spark, SMALL), fixtures.nodes(spark, SMALL)
    runs = nodes.select(F.col("node").alias("run"), F.col("node").alias("source"), F.lit(700).cast("long").alias("radius"))
    shipped = spark.sparkContext.accumulator(0)

    def solve(net, rows):
        shipped.add(len(net.dst))
        return search._reach_rows(net, rows, True)

    own = runs.withColumn("targets", F.array().cast("array<long>"))
    got = set(map(tuple, search._by_disk(edges, own, nodes, solve, search._REACH).collect()))
    assert got == set(map(tuple, search.reach(edges, runs, "broadcast").collect()))
    assert shipped.value < 6 * edges.count()


def test_edges_reach_their_cells_packed(spark):
    """What is written for other tasks is rows of many edges: each edge used to be written five times on its own."""
    edges, nodes = fixtures.edges(spark, LESS_SMALL), fixtures.nodes(spark, LESS_SMALL)
    runs = spark.createDataFrame([(7, 7, 2000), (8, 1499, 900)], "run long, source long, radius long")
    stages, none = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0)

    def written():
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        own = stages.stageList(None, False, False, none, None)
        return sum(own.apply(k).shuffleWriteRecords() for k in range(own.size()))

    before = written()
    got = set(map(tuple, search.reach(edges, runs, "disk", nodes).collect()))
    after = written()
    assert after - before < nodes.count() + edges.count() / 4
    assert got == set(map(tuple, search.reach(edges, runs, "broadcast").collect()))


def test_packed_columns_come_back():
    first, second, third = np.array([-5, 3, 1 << 40]), np.array([1, -(1 << 50), 7]), np.array([0.5, -1e300, 3.0])
    rows = [d for _, d in sorted(search._groups(np.array([2, 1, 1]), first, second, third))]
    assert [v.tolist() for v in search.unpack(rows, "lld")] == [[3, 1 << 40, -5], [-(1 << 50), 7, 1], [-1e300, 3.0, 0.5]]
    assert [len(v) for v in search.unpack([], "ld")] == [0, 0]


def test_formulas_and_rings_read_their_tables(spark):
    for f, name in ((queries.process_formula, "lineitem"), (queries.ring_layers, "customer"), (queries.sql_functions, "customer")):
        assert any(p.endswith(f"{name}.parquet") for p in f(spark, SMALL).inputFiles()), name
    formulas = queries.process_formula(spark, SMALL).collect()
    assert sum(r.lines for r in formulas) == 6000
    assert all(r.published == r.n * (r.n * r.m + 2) and r.layered == sum(a * b for a, b in zip([1, *[r.n] * r.m], [*[r.n] * r.m, 1])) for r in formulas)
    places = [(n % 15 // 4, n // 15 // 4) for n in range(150)]
    want = {k: sum(max(abs(i - a), abs(j - b)) == k for a, b in places for i in range(4) for j in range(3)) for k in (1, 2, 3)}
    assert dict(map(tuple, queries.ring_layers(spark, SMALL).collect())) == want


def test_layers_of_a_long_trip_keep_small_plans(spark, monkeypatch):
    """What a layer costs the driver does not grow with the layers before it; trips may end at different ones."""
    rng, rows = np.random.default_rng(3), []
    for trip, last in ((0, 21), (1, 1), (2, 0), (3, 9)):
        places = [[planner.SOURCE], *[list(range(10, 13)) for _ in range(last)], [planner.TARGET]]
        rows += [(trip, k, u, v, int(rng.integers(1, 4)), 0.0) for k in range(last + 1) for u in places[k] for v in places[k + 1] if u != v]
    rows += [(4, k, k - 1, k, 1, 0.0) for k in range(5)]  # never arrives
    edges = spark.createDataFrame(rows, "trip long, layer int, u long, v long, weight long, weight_adj double")
    plans, cut = [], search.cut

    def seen(df):
        plans.append(len(df._jdf.queryExecution().logical().toString()))
        return cut(df)

    monkeypatch.setattr(search, "cut", seen)
    monkeypatch.setattr(planner, "cut", seen)
    got = planner.final_path(edges, mode="layers")
    few, plans[:] = max(plans), []
    assert sorted(map(tuple, got.select("trip", "layer", "u", "v").collect())) == sorted(map(tuple, planner.final_path(edges).select("trip", "layer", "u", "v").collect()))
    planner.final_path(edges.where("layer < 10"), mode="layers")
    assert few <= 1.1 * max(plans)
