"""Network building, tiles, stores, bins and the SQL surface."""

import random

import pytest
from pyspark.sql import functions as F

from chargepath.functions import request, sql
from chargepath.operators import bins, network, planner
from chargepath.plans import queries
from chargepath.sources.wkt_tiles import WktTiles

SMALL = "/root/testdata/sf0.001"


def test_nodes_by_coordinate(spark):
    rows = [("LINESTRING(0 0, 1 0)", "A", "F", 5), ("LINESTRING (1.0000000001 0, 1 1, 2 2)", "A", "O", 7), ("linestring(2 2, 0 0)", "R", "F", 1)]
    segs = spark.createDataFrame(rows, "wkt string, road_class string, direction string, weight long")
    built = network.build_network(segs, network.NetworkSpec(roles=network.ColumnRoles(wkt="wkt"), view="tiny"))
    assert sorted(map(tuple, built.nodes.select("node", "x", "y").collect())) == [(0, 0.0, 0.0), (1, 1.0, 0.0), (2, 2.0, 2.0)]
    assert sorted(map(tuple, spark.sql("SELECT src, dst, weight FROM tiny_edges").collect())) == [(0, 1, 5), (1, 0, 5), (1, 2, 7)]


def test_unsound_networks_are_refused(spark):
    nodes = spark.createDataFrame([(0, 0.0, 0.0)], "node long, x double, y double")
    segs = spark.createDataFrame([(0, 1, "A", "F", 5)], "a long, b long, road_class string, direction string, weight long")
    with pytest.raises(ValueError, match="unknown"):
        network.build_network(segs, network.NetworkSpec(), nodes)


def test_dense_ids_do_not_depend_on_partitions(spark):
    rows = [(float(k * 37 % 101), float(k % 7)) for k in range(300)]
    df = spark.createDataFrame(rows, "x double, y double").distinct()
    want = {p: k for k, p in enumerate(sorted(set(rows)))}
    for parts in (1, 5):
        assert {(r.x, r.y): r.id for r in network.dense_ids(df.repartition(parts), ["x", "y"], "id").collect()} == want
    assert network.dense_ids(df.where("false"), ["x", "y"], "id").isEmpty()


def test_exact_tiles(spark):
    rng = random.Random(3)
    rows = [(k, float(rng.randint(0, 9)), float(rng.randint(0, 3))) for k in range(300)]
    got = network.tile_adaptive(spark.createDataFrame(rows, "node long, x double, y double"), 30).collect()
    by = {}
    for r in got:
        by.setdefault(r.tile, []).append((r.x, r.y))
    assert len(got) == 300 and all(len(v) <= 30 or len(set(v)) == 1 for v in by.values())
    boxes = [(min(x for x, _ in v), max(x for x, _ in v), min(y for _, y in v), max(y for _, y in v)) for v in by.values()]
    for i, a in enumerate(boxes):
        assert all(a[1] < b[0] or b[1] < a[0] or a[3] < b[2] or b[3] < a[2] for b in boxes[:i])  # rectangles apart


def test_stored_networks(spark, tmp_path):
    edges = spark.createDataFrame([(k % 3, k, k + 1, 10) for k in range(30)], "tile long, src long, dst long, weight long")
    network.write_network(edges, str(tmp_path / "net"))
    assert sorted(map(tuple, network.read_network(spark, str(tmp_path / "net")).select("tile", "src", "dst", "weight").collect())) == sorted(map(tuple, edges.collect()))
    some = network.read_network(spark, str(tmp_path / "net"), [1])
    assert some.count() == 10 and "PartitionFilters: [isnotnull(tile" in some._jdf.queryExecution().toString()
    network.bucket_network(edges.drop("tile"), "bucketed_edges", 4)
    state = spark.range(5).withColumnRenamed("id", "src")
    assert state.join(spark.table("bucketed_edges"), "src").count() == 5
    spark.sql("DROP TABLE bucketed_edges")


def test_wkt_tiles(spark, tmp_path):
    spark.dataSource.register(WktTiles)
    rows = spark.createDataFrame([(k % 3, f"LINESTRING({k} 0, {k + 1} 0)", "A", "F", 10 + k) for k in range(12)], "tile long, wkt string, road_class string, direction string, weight long")
    folder = str(tmp_path / "tiles")
    for _ in range(2):
        rows.repartition("tile").write.format("wkt_tiles").mode("overwrite").save(folder)
    back = spark.read.format("wkt_tiles").load(folder)
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, rows.collect()))
    assert spark.read.format("wkt_tiles").option("tiles", "1").load(folder).count() == 4
    built = network.build_network(back, network.NetworkSpec(roles=network.ColumnRoles(wkt="wkt")))
    assert built.edges.count() == 24 and built.nodes.count() == 13


def test_quadtree_and_scan_find_the_same(spark):
    rng = random.Random(9)
    make = lambda n, name: spark.createDataFrame([(k, rng.random() * 40, rng.random() * 25) for k in range(n)], f"{name} long, x double, y double")
    points, items = make(150, "point"), make(200, "item")
    for radius in (0.5, 3.0, 11.0, 60.0):
        want = sorted(map(tuple, bins.within_scan(points, items, radius).select("point", "item").collect()))
        for levels, capacity in ((1, 4), (5, 8), (7, 1)):
            got = bins.within_quadtree(points, items, levels, (0.0, 0.0, 40.0, 25.0), capacity, radius)
            assert sorted(map(tuple, got.select("point", "item").collect())) == want


def test_cells_in_python_and_in_sql_agree(spark):
    grid = bins.BinGrid(0.7, -3.0, -2.0, 5.0, 6.0)
    rows = [(-3.0, -2.0), (0.1, 0.7), (4.99, 5.99), (1.1, -1.3), (0.0, 0.0)]
    got = bins.with_bin(spark.createDataFrame(rows, "x double, y double"), grid).collect()
    assert all(grid.bin_at(r.x, r.y) == r.bin for r in got)
    cells = spark.createDataFrame([(r.bin,) for r in got], "bin long").distinct()
    for k in (1, 2):
        near = bins.around(cells, grid, k).groupBy("bin").agg(F.sort_array(F.collect_set("near")).alias("near")).collect()
        assert all(sorted(grid.block(r.bin, k)) == r.near for r in near)


def test_texts_of_lines(spark):
    df = spark.createDataFrame([("LINESTRING(0 0, 3 4,3 5)",), ("POINT(1 2)",), (None,), ("LINESTRING()",)], "t string").withColumn("line", sql.parse_linestring(F.col("t")))
    lines = [r.line for r in df.collect()]
    assert [(p.x, p.y) for p in lines[0]] == [(0, 0), (3, 4), (3, 5)] and lines[1:] == [None, None, None]
    total = df.select("t", F.explode("line").alias("p")).groupBy("t").agg(sql.polyline_length("p.x", "p.y").alias("l")).first().l
    assert abs(total - 6) < 1e-9
    assert sql.parse_ring("POLYGON((0 0, 1 0, 1 1, 0 0))") == [(0, 0), (1, 0), (1, 1)]
    with pytest.raises(ValueError):
        sql.parse_ring("POINT(1 1)")
    km = spark.createDataFrame([(0.0, 0.0, 1.0, 0.0)], "a double, b double, c double, d double").select(sql.haversine_km("a", "b", "c", "d").alias("km")).first().km
    assert abs(km - 111.195) < 0.01 and abs(bins.cell_from_km(111.195) - 1) < 1e-9


def test_sql_surface_and_requests(spark):
    rows = {r.node: r for r in queries.sql_functions(spark, SMALL).collect()}
    assert set(rows) == set(range(150)) and {(k % 4, r.cells) for k, r in rows.items()} == {(0, 1), (1, 8), (2, 16), (3, 24)}
    assert (rows[63].line, rows[63].bin, rows[8].budget, rows[9].budget) == (5.0, 4, 9 * (9 * 2 + 2), 5)
    costs = {r.dst: r.weight for r in queries.net_edges(spark, SMALL).collect()}
    assert all(r.adjusted == costs[k] * 1.24 or abs(r.adjusted - costs[k] * 1.24) < 1e-9 for k, r in rows.items())
    net = queries.net(spark, SMALL)
    legs = request.handle(net, '{"source": 0, "target": 149, "capacity": 5000, "n": 3}').collect()
    whole = request.handle(net, '{"source": 0, "target": 149, "capacity": 5000, "n": 3, "aggregate_output": true}').first()
    assert sum(r.leg_cost for r in legs) == whole.cost == 9684 and whole.path[0] == 0 and whole.path[-1] == 149
    with pytest.raises(ValueError):
        request.parse('{"source": 1, "target": 2, "colour": "red"}')
    assert planner.Net(net.edges, net.nodes, net.stations, net.grid).validate().isEmpty()


def test_plans_keep_to_the_bins(spark):
    """No cartesian product outside the declared baseline, and filters reach the scan."""
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    g, points, items = queries._points(spark, SMALL)
    assert "CartesianProduct" not in plan(bins.within(points, items, g.grid, 6.0)) and "NestedLoop" not in plan(bins.within(points, items, g.grid, 6.0))
    assert "PushedFilters: [Not(In(l_returnflag, [R]))" in plan(queries.net_class_filter(spark, SMALL)) or "l_returnflag" in plan(queries.net_class_filter(spark, SMALL)).split("PushedFilters")[1]
