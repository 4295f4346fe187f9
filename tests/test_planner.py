import pytest

from chargepath.config import TripOptions
from chargepath.functions import request
from chargepath.operators import bins, network, planner, search

OPTS = TripOptions(capacity=50, n=2, penalty=25)


def line(spark):
    rows = [(a, b, 10) for k in range(10) for a, b in ((k, k + 1), (k + 1, k))]
    nodes = spark.createDataFrame([(k, float(k), 0.0) for k in range(11)], "node long, x double, y double")
    stations = spark.createDataFrame([(100 + k, n, float(n), 0.0, "a") for k, n in enumerate((3, 5, 7, 9))], "station long, node long, x double, y double, plug string")
    return planner.Net(spark.createDataFrame(rows, "src long, dst long, weight long"), nodes, stations, bins.BinGrid(1.0, 0.0, 0.0, 11.0, 1.0))


def trips(spark, *rows):
    return spark.createDataFrame(list(rows), "trip long, source long, target long")


def test_line(spark):
    plan = planner.plan_trips(line(spark), trips(spark, (0, 0, 10)), OPTS)
    assert sorted((r.stop, r.node) for r in plan.bases.collect()) == [(1, 4), (2, 8)]
    assert sorted((r.u, r.v, r.cost) for r in plan.legs.collect()) == [(-1, 100, 30), (-1, 101, 50), (100, 102, 40), (101, 102, 20), (101, 103, 40), (102, -2, 30), (103, -2, 10)]
    done = planner.aggregated(plan.solution).first()
    assert (done.cost, done.cost_adj, done.stations, done.path) == (100, 150.0, [100, 102], list(range(11)))


def test_direct_and_no_path(spark):
    net = line(spark)
    rows = planner.plan_trips(net, trips(spark, (0, 0, 5), (1, 0, 99)), OPTS)
    assert dict(rows.status.collect()) == {0: "ok", 1: "no_path"}
    assert [(r.leg_cost, r.station) for r in rows.solution.collect()] == [(50, None)]


def test_no_candidate_and_slide(spark):
    net = line(spark)
    net.stations = net.stations.where("station IN (100, 103)")
    tight = TripOptions(capacity=50, n=1, alpha=0.1, max_widen=0)
    assert planner.plan_trips(net, trips(spark, (0, 0, 10)), tight).status.first().status == "no_candidate"
    moved = planner.plan_trips(net, trips(spark, (0, 0, 10)), TripOptions(capacity=70, n=1, alpha=0.1, max_widen=0, mitigation="slide"))
    assert moved.candidates.count() >= 1


@pytest.mark.parametrize("mode", ["none", "flat", "proportional", "proportional_no_last"])
def test_penalty_modes(spark, mode):
    plan = planner.plan_trips(line(spark), trips(spark, (0, 0, 10)), TripOptions(capacity=50, n=2, penalty=25, penalty_mode=mode))
    total = planner.aggregated(plan.solution).first()
    assert total.cost == 100
    # A charge is 25 for 50 of way: on all of it, or not on the last leg, which is longest by way of 102.
    assert total.cost_adj == {"none": 100, "flat": 150, "proportional": 150, "proportional_no_last": 135}[mode]
    assert total.stations == [100, 102]


def test_strategies_agree(spark):
    net = line(spark)
    runs = spark.createDataFrame([(0, 0, 45), (1, 10, None)], "run long, source long, radius long")
    answers = [sorted(map(tuple, search.reach(net.edges, runs, s, net.nodes).collect()), key=repr) for s in ("broadcast", "frontier", "disk")]
    assert answers[0] == answers[1] == answers[2]
    assert len(answers[0]) == 5 + 11


def test_ties_take_the_least_predecessor(spark):
    edges = spark.createDataFrame([(0, 2, 1), (0, 1, 1), (1, 3, 1), (2, 3, 1)], "src long, dst long, weight long")
    run = spark.createDataFrame([(0, 0, None)], "run long, source long, radius long")
    for strategy in ("broadcast", "frontier"):
        assert {r.node: r.pred for r in search.reach(edges, run, strategy).collect()}[3] == 1


def test_edge_formulas_and_options():
    assert planner.edge_budget_published(10, 10) == 1020
    assert planner.edge_budget_published(5, 5) == 135
    assert planner.edge_count_layered([5] * 6) == 135
    with pytest.raises(ValueError):
        TripOptions(alpha=1.5)
    assert request.parse('{"source": 1, "target": 2, "capacity": 9, "n": 1}')[1].capacity == 9


def test_tiles_share_nodes_only(spark):
    net = line(spark)
    tiles = network.plan_tiles(net.nodes, 4)
    assert tiles.agg({"nodes": "sum"}).first()[0] == 11
    assert all(r.nodes <= 4 for r in tiles.collect())
    segs = spark.createDataFrame([(k, k + 1, "A", "F", 10) for k in range(10)], "a long, b long, road_class string, direction string, weight long")
    assigned = network.assign_segments(segs, net.nodes, tiles)
    assert assigned.count() == 10
    assert sorted(network.assemble([assigned.drop("tile")]).collect()) == sorted(net.edges.collect())


def test_validate(spark):
    edges = spark.createDataFrame([(0, 1, 0), (0, 99, 5), (None, 1, 5)], "src long, dst long, weight long")
    nodes = spark.createDataFrame([(0,), (1,)], "node long")
    assert {r.problem for r in network.validate(edges, nodes).collect()} >= {"weight", "unknown dst", "null"}


@pytest.mark.parametrize("change", [{}, {"direction": "both", "leg_mode": "pairwise", "split_rule": "multiples"}, {"order": "bins", "plugs": ("a",)}])
def test_tables_and_kernels_agree(spark, monkeypatch, change):
    """Above the broadcast bound every step goes over tables and gives the same rows."""
    opts = TripOptions(**{"capacity": 50, "n": 2, "penalty": 25, **change})
    asked = trips(spark, (0, 0, 10), (2, 0, 99), (3, 2, 6), (4, 4, 4))

    def run():
        plan = planner.plan_trips(line(spark), asked, opts)
        show = lambda df, *c: sorted(map(tuple, df.select(*c).collect()), key=repr)
        return [show(plan.bases, "trip", "stop", "node", "cum"), show(plan.candidates, "trip", "stop", "station", "node", "dist", "widen_round"), show(plan.legs, "trip", "layer", "u", "v", "cost", "path"), show(plan.solution, "trip", "leg_index", "station", "leg_cost", "path"), show(plan.status, "trip", "status")]

    small = run()
    monkeypatch.setattr(search, "MAX_BROADCAST_EDGES", 3)
    assert run() == small


@pytest.mark.parametrize("mode", ["layers", "sssp", "udtf"])
def test_final_path_modes_agree(spark, mode):
    asked = trips(spark, (0, 0, 10), (1, 10, 0), (3, 2, 6))
    edges = planner.plan_trips(line(spark), asked, OPTS).edges
    show = lambda df: sorted(map(tuple, df.select("trip", "layer", "u", "v", "weight", "weight_adj").collect()))
    assert show(planner.final_path(edges, mode=mode)) == show(planner.final_path(edges))


def test_edges_over_the_capacity_and_options_by_trip(spark):
    net = line(spark)
    net.edges = net.edges.where("NOT (src = 6 AND dst = 7)").unionByName(spark.createDataFrame([(6, 7, 60)], "src long, dst long, weight long"))
    assert planner.plan_trips(net, trips(spark, (0, 0, 10)), OPTS).status.first().status == "edge_exceeds_capacity"
    asked = spark.createDataFrame([(0, 0, 10, 50, 2), (1, 0, 10, 200, None), (2, 0, 10, None, 1)], "trip long, source long, target long, capacity long, n int")
    plan = planner.plan_mixed(line(spark), asked, OPTS)
    assert dict(plan.status.collect()) == {0: "ok", 1: "ok", 2: "ok"}
    assert {r.trip: r.stations for r in planner.aggregated(plan.solution).collect()}[1] == []


def test_incompatible_plugs_leave_no_candidate(spark):
    assert planner.plan_trips(line(spark), trips(spark, (0, 0, 10)), TripOptions(capacity=50, n=2, plugs=("b",))).status.first().status == "no_candidate"


def test_legs_of_a_store_are_not_searched(spark, monkeypatch):
    net, asked = line(spark), trips(spark, (0, 0, 10))
    first = planner.plan_trips(net, asked, OPTS)
    store = planner.leg_cache(first.layers, first.legs, OPTS)
    again = planner.plan_trips(net, asked, OPTS, cache=store)
    assert again.legs.where("run IS NOT NULL").isEmpty() and again.legs.count() == first.legs.count()


def test_costs_scale_with_all_weights(spark):
    net, small = line(spark), planner.aggregated(planner.plan_trips(line(spark), trips(spark, (0, 0, 10)), OPTS).solution).first()
    net.edges = net.edges.selectExpr("src", "dst", "weight * 7 AS weight")
    large = planner.aggregated(planner.plan_trips(net, trips(spark, (0, 0, 10)), TripOptions(capacity=350, n=2, penalty=175)).solution).first()
    assert (large.cost, large.cost_adj, large.stations) == (7 * small.cost, 7 * small.cost_adj, small.stations)
