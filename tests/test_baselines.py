from chargepath.operators import baselines, bins, planner, search
from chargepath.plans import queries
from chargepath.sources import fixtures


def line(spark, n):
    """n + 1 nodes ten apart in both directions, a station at each but the ends."""
    edges = spark.createDataFrame([(a, b, 10) for k in range(n) for a, b in ((k, k + 1), (k + 1, k))], "src long, dst long, weight long")
    nodes = spark.createDataFrame([(k, float(k), 0.0) for k in range(n + 1)], "node long, x double, y double")
    stations = spark.createDataFrame([(100 + k, k, float(k), 0.0, "a") for k in range(1, n)], "station long, node long, x double, y double, plug string")
    return planner.Net(edges, nodes, stations, bins.BinGrid(1.0, 0.0, 0.0, n + 1.0, 1.0))


def line_of(net):
    """The same network, not loaded yet."""
    return planner.Net(net.edges, net.nodes, net.stations, net.grid)


def test_greedy_trips_of_any_length_arrive(spark):
    trips = spark.createDataFrame([(0, 0, 70), (1, 60, 70), (2, 70, 0)], "trip long, source long, target long")
    got = {r.trip: (r.cost, r.stops) for r in baselines.greedy_trip(line(spark, 70), trips, 10).collect()}
    assert got == {0: (700, 69), 1: (100, 9), 2: (700, 69)}


def test_exact_costs_are_the_same_over_the_broadcast_bound(spark, monkeypatch):
    net = line(spark, 9)
    net.stations = net.stations.where("node NOT IN (4, 5)")
    trips = spark.createDataFrame([(0, 0, 9), (1, 5, 5), (2, 4, 0), (3, 9, 1), (4, 4, 5)], "trip long, source long, target long")
    # Nodes 3 and 6 are 30 apart: trip 0 and 3 can pass with 30, not with 20.
    want = {30: {0: 90, 1: 0, 2: 40, 3: 80, 4: 10}, 20: {1: 0, 2: 40, 4: 10}}
    for capacity in want:
        assert dict(baselines.exact_optimum(line_of(net), trips, capacity).collect()) == want[capacity]
    monkeypatch.setattr(search, "load", lambda *a, **k: None)
    for capacity in want:
        assert dict(baselines.exact_optimum(line_of(net), trips, capacity).collect()) == want[capacity]


def test_bidirectional_costs_are_the_same_over_the_broadcast_bound(spark, monkeypatch):
    net = line(spark, 9)
    trips = spark.createDataFrame([(0, 0, 9), (1, 5, 5), (2, 4, 0), (3, 0, 77)], "trip long, source long, target long")
    monkeypatch.setattr(fixtures, "edges", lambda *a: net.edges)
    monkeypatch.setattr(fixtures, "nodes", lambda *a: net.nodes)
    monkeypatch.setattr(fixtures, "batch_trips", lambda *a: trips)
    monkeypatch.setattr(search, "load", lambda *a, **k: None)
    assert sorted(map(tuple, queries.bidirectional_cost(spark, "").collect())) == [(0, 9, 90), (1, 5, 0), (2, 0, 40), (3, 77, None)]
