"""Plans of very many trips by arrays, against the steps of single searches."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from chargepath.config import TripOptions
from chargepath.operators import planner, search, separators
from chargepath.plans import queries
from chargepath.sources import fixtures
from tests.test_planner import line, trips

SMALL = "/root/testdata/sf0.001"


def random_network(seed: int, ties: bool) -> search.Network:
    """Points with short edges, some alone, some apart from the rest."""
    rng = np.random.default_rng(seed)
    n = 300
    x, y = rng.random(n) * 20, rng.random(n) * 20
    near = np.argsort(np.hypot(x[:, None] - x, y[:, None] - y), axis=1)[:, 1:4]
    src, dst = np.repeat(np.arange(n), 3), near.ravel()
    kept = rng.random(len(src)) < 0.8
    weight = rng.integers(1, 3 if ties else 50, len(src))
    ids = np.sort(rng.choice(5000, n, replace=False))
    return search.Network(ids[src[kept]], ids[dst[kept]], weight[kept], (ids, x, y))


@pytest.mark.parametrize("ties", [False, True])
def test_closed_cells_give_the_paths_of_single_searches(ties):
    for seed in range(4):
        net = random_network(seed, ties)
        there = separators.Closed(net, leaf=12)
        sources = np.arange(0, len(there.nodes), 7)
        dist = there.distances(sources)
        for column, s in enumerate(sources):
            found = search.bounded(net, int(there.nodes[s]))
            assert {int(v): int(d) for v, d in zip(there.nodes, dist[:, column], strict=True) if d < there.FAR} == found.dist
            ends = np.flatnonzero(dist[:, column] < there.FAR)
            pair, at, cum = there.routes(dist, np.full(len(ends), column), ends)
            for k, end in enumerate(ends):
                path = search.trace(found.pred, int(there.nodes[end]))
                assert there.nodes[at[pair == k]].tolist() == path and cum[pair == k].tolist() == [found.dist[v] for v in path]


@pytest.mark.parametrize("change", [{}, {"split_rule": "multiples"}, {"tail_rule": "capacity"}, {"direct_if_within": False}])
def test_paths_are_cut_alike(spark, change):
    opts = TripOptions(**{"capacity": 50, "n": 2, **change})
    rng = np.random.default_rng(5)
    ways = [np.r_[0, np.cumsum(rng.choice([3, 10, 39, 40, 41, 90], k))].tolist() for k in range(12) for _ in range(8)]
    path = spark.createDataFrame([(k, w[-1], list(range(len(w))), w) for k, w in enumerate(ways)], "trip long, cost long, path array<long>, cum array<long>")
    want = {r.trip: r.at for r in planner.split_bases(path, opts).groupBy("trip").agg(F.array_sort(F.collect_list("pos")).alias("at")).collect()}
    assert {k: c for k, w in enumerate(ways) if (c := planner.cut_points(np.array(w), opts))} == want


def both(net, asked, opts):
    plan = planner.plan_trips(net, asked, opts)
    cost = plan.solution.groupBy("trip").agg(F.sum("leg_cost").alias("cost"))
    want = plan.status.join(cost, "trip", "left").join(plan.path.select("trip", F.col("cost").alias("direct")), "trip", "left")
    got = planner.costs_of(net, asked, opts, single=0).select("trip", "status", "cost", "direct")
    return sorted(map(tuple, got.collect())), sorted(map(tuple, want.collect()))


@pytest.mark.parametrize("change", [{}, {"n": 5, "max_widen": 0}, {"capacity": 1100, "alpha": 0.3}, {"direction": "both", "split_rule": "multiples", "leg_limit": "beta"}])
def test_many_plans_equal_single_plans(spark, monkeypatch, change):
    opts = TripOptions(**{"capacity": 1500, "n": 3, **change})
    net, asked = queries.net(spark, SMALL), fixtures.batch_trips(spark, SMALL)
    want = both(net, asked, opts)[1]
    monkeypatch.setattr(planner, "plan_trips", None)  # every trip goes by arrays
    got = planner.costs_of(net, asked, opts, single=0).select("trip", "status", "cost", "direct")
    assert sorted(map(tuple, got.collect())) == want and len({r[1] for r in want} | {"ok"}) >= 1


def test_every_status(spark):
    opts = TripOptions(capacity=50, n=2, penalty=25)
    asked = trips(spark, (0, 0, 10), (1, 0, 5), (2, 0, 99), (3, 4, 4), (4, 99, 99), (5, 10, 0), (6, 3, 9))
    net = line(spark)
    got, want = both(net, asked, opts)
    assert got == want and {r[1] for r in got} == {"ok", "no_path"}
    net = line(spark)
    net.edges = net.edges.where("NOT (src = 6 AND dst = 7)").unionByName(spark.createDataFrame([(6, 7, 60)], "src long, dst long, weight long"))
    got, want = both(net, asked, opts)
    assert got == want and "edge_exceeds_capacity" in {r[1] for r in got}
    net = line(spark)
    net.stations = net.stations.where("station IN (100, 103)")
    for tight in (TripOptions(capacity=50, n=1, alpha=0.1, max_widen=0), TripOptions(capacity=50, n=1, max_widen=2)):
        got, want = both(net, asked, tight)
        assert got == want and {"no_candidate", "no_leg_chain"} & {r[1] for r in got}


def test_batches_go_by_arrays(spark, monkeypatch):
    """Very many urgent trips start no single search of a path."""
    monkeypatch.setattr(separators, "SINGLE", 0)
    monkeypatch.setattr(planner, "initial_path", None)
    for name in ("plan_batch", "plan_infeasible", "feasible_share", "stream_plans"):
        assert queries.QUERIES[name](spark, SMALL).count() > 0
