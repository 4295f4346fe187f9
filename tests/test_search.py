"""All search strategies against each other on random networks, ties and isolated nodes included."""

import random

import numpy as np
import pytest

from chargepath.operators import iterate, overlay, search, separators


def network(spark, seed, n=40, few=4):
    rng = random.Random(seed)
    spots = [(k, float(rng.randint(0, 12)), float(rng.randint(0, 12))) for k in range(n + 2)]  # the last two have no edges
    arcs = {(rng.randrange(n), rng.randrange(n)): rng.randint(1, few) for _ in range(3 * n)}
    rows = [(a, b, w) for (a, b), w in arcs.items() if a != b]
    return spark.createDataFrame(rows, "src long, dst long, weight long"), spark.createDataFrame(spots, "node long, x double, y double"), rows


def shortest(rows, source):
    """Bellman-Ford with the least predecessor."""
    dist, changed = {source: 0}, True
    while changed:
        changed = False
        for a, b, w in rows:
            if a in dist and dist[a] + w < dist.get(b, 1 << 60):
                dist[b], changed = dist[a] + w, True
    pred = {v: min((a for a, b, w in rows if b == v and a in dist and dist[a] + w == d), default=None) for v, d in dist.items()}
    pred[source] = None
    return dist, pred


@pytest.mark.parametrize("seed", [1])
def test_reach_of_all_strategies(spark, seed):
    edges, nodes, rows = network(spark, seed)
    runs = [(0, 0, 4), (1, 5, 2), (2, 41, 9), (3, 7, 0), (4, 9, None)]
    want = set()
    for run, source, radius in runs:
        dist, pred = shortest(rows, source)
        want |= {(run, v, d, pred[v]) for v, d in dist.items() if radius is None or d <= radius}
    table = spark.createDataFrame(runs, "run long, source long, radius long")
    for strategy in ("broadcast", "disk", "frontier", "delta"):
        assert set(map(tuple, search.reach(edges, table, strategy, nodes, delta=2).collect())) == want, strategy
    assert {tuple(r) for r in search.reach(edges, table, "broadcast", history=False).collect()} == {w[:3] for w in want}


@pytest.mark.parametrize("seed", [3])
def test_paths_of_all_strategies(spark, seed, monkeypatch):
    edges, nodes, rows = network(spark, seed)
    asked = [(k, k % 40, [(7 * k + 3) % 42], None if k % 3 else 6) for k in range(30)] + [(99, 0, [1, 5, 9, 41], None)]
    want = set()
    for run, source, targets, radius in asked:
        dist, pred = shortest(rows, source)
        for t in targets:
            if t in dist and (radius is None or dist[t] <= radius):
                want.add((run, t, dist[t], tuple(search.trace(pred, t))))
    runs = spark.createDataFrame(asked, "run long, source long, targets array<long>, radius long")
    show = lambda df: {(r.run, r.target, r.cost, tuple(r.path)) for r in df.collect()}
    assert show(search.paths(edges, runs)) == want
    assert show(search.paths(edges, runs, nodes)) == want  # goal-directed where there is one target
    monkeypatch.setattr(search, "MAX_BROADCAST_EDGES", 1)
    some = runs.where("radius IS NOT NULL")
    assert show(search.paths(edges, some, nodes)) == {w for w in want if w[0] in {a[0] for a in asked if a[3] is not None}}  # by disks
    single = runs.where("size(targets) = 1")
    assert show(search.paths(edges, single, nodes)) == {w for w in want if w[0] != 99}  # the frontier with target stop and goal
    assert show(search.paths(edges, runs)) == want


def test_two_sided_dense_and_goal_directed_searches(spark):
    edges, nodes, rows = network(spark, 6, few=9)
    net = search.load(edges, nodes).value
    back = net.flipped()
    for s in range(0, 40, 3):
        dist, pred = shortest(rows, s)
        far, settled = search.dense(net, s, 42)
        assert settled == len(dist) and {v: d for v, d in enumerate(far.tolist()) if d < 1 << 60} == dist
        for t in range(42):
            cost, _ = search.bidirectional(net, back, s, t, net.goal(s), net.goal(t))
            assert cost == dist.get(t) == search.bidirectional(net, back, s, t)[0]
            found = search.bounded(net, s, None, [t], net.goal(t))
            if t in dist:
                assert search.trace(found.pred, t) == search.trace(pred, t)


def test_goal_directed_ties(spark):
    edges = spark.createDataFrame([(1, 9, 2), (1, 5, 2), (9, 0, 2), (5, 0, 2)], "src long, dst long, weight long")
    net = search.load(edges).value
    bound = {0: 0, 9: 1, 5: 2, 1: 3}.get
    assert search.trace(search.bounded(net, 1, None, [0], bound).pred, 0) == [1, 5, 0]


def test_overlay_equals_the_whole_network(spark):
    edges, _, rows = network(spark, 8)
    tiled = spark.createDataFrame([(a % 3, a, b, w) for a, b, w in rows], "tile long, src long, dst long, weight long")
    asked = [(k, k, (5 * k + 1) % 42) for k in range(40)]
    trips = spark.createDataFrame(asked, "trip long, source long, target long")
    want = {}
    for k, s, t in asked:
        dist, _ = shortest(rows, s)
        if t in dist:
            want[k] = dist[t]
    assert dict(overlay.distances(tiled, overlay.build(tiled), trips).collect()) == want


def test_overlay_stays_out_of_the_driver(spark, monkeypatch):
    """No network is loaded there, and sources come in as many goes as its share of costs allows."""
    edges, _, rows = network(spark, 11)
    tiled = spark.createDataFrame([((a + b) % 3, a, b, w << 40) for a, b, w in rows], "tile long, src long, dst long, weight long")
    asked = [(k, k, (9 * k + 2) % 42) for k in range(12)] + [(90, 7, 7), (91, 41, 3)]
    trips = spark.createDataFrame(asked, "trip long, source long, target long")

    def refused(*args, **more):
        raise AssertionError("a network on the driver")

    monkeypatch.setattr(search, "load", refused)
    monkeypatch.setattr(overlay, "ENTRIES", 200)
    whole = {s: shortest(rows, s)[0] for _, s, _ in asked}
    assert dict(overlay.distances(tiled, overlay.build(tiled), trips).collect()) == {k: whole[s][t] << 40 for k, s, t in asked if t in whole[s]}


def test_links_end_at_nodes_left_without_a_predecessor(spark):
    """5 fell in cost after its neighbour 6 was reached and was not relaxed again, as it lies over the stop."""
    found = spark.createDataFrame([(0, 1, 0, None), (0, 2, 3, 1), (0, 6, 9, None), (0, 7, 11, 6)], "run long, node long, dist long, pred long")
    ends = spark.createDataFrame([(0, 2)], "run long, target long")
    assert sorted(map(tuple, search.backtrace(found, ends).collect())) == [(0, 2, 1, 0), (0, 2, 2, 3)]


def test_iterate(spark):
    state = spark.createDataFrame([(1,), (6,)], "n long")
    done, rounds = iterate.iterate(state, lambda s, k: s.selectExpr("CASE WHEN n > 0 THEN n - 1 ELSE n END AS n"), "n > 0", every=2)
    assert rounds == 6 and [r.n for r in done.collect()] == [0, 0]
    with pytest.raises(RuntimeError):
        iterate.iterate(state, lambda s, k: s, "n > 0", most=2)


def test_separating_nodes_equal_single_searches(spark):
    edges, nodes, rows = network(spark, 11, few=9)
    there = spark.sparkContext.broadcast(separators.Parted(search.load(edges, nodes).value, 4))
    assert len(there.value.levels) > 2
    asked = [(100 * s + t, s, t) for s in range(42) for t in range(42)]
    want = {100 * s + t: d for s in range(42) for t, d in shortest(rows, s)[0].items()}
    assert dict(separators.costs(there, spark.createDataFrame(asked, "trip long, source long, target long")).collect()) == want
    assert separators.parted(edges, nodes, 10) is None and separators.parted(edges, nodes, 10, single=1) is not None


@pytest.mark.parametrize("size", [4, 1000])
def test_frontier_by_blocks(spark, monkeypatch, size):
    """Rounds go by blocks, with stops, radii, several runs a block, places that are not known and runs without an edge."""
    import numpy as np

    monkeypatch.setattr(search, "BLOCK_NODES", size)
    monkeypatch.setattr(search, "BLOCK_RUNS", 2)
    rng = np.random.default_rng(3)
    steps = [(int(a), int(b), int(w)) for a, b, w in zip(rng.integers(0, 40, 120), rng.integers(0, 40, 120), rng.integers(1, 9, 120)) if a != b]
    edges = spark.createDataFrame(steps, "src long, dst long, weight long")
    nodes = spark.createDataFrame([(k, float(k % 7), float(k // 7)) for k in range(38)], "node long, x double, y double")
    runs = spark.createDataFrame([(0, 0, [39], None), (1, 5, [17], None), (2, 9, [30], 12), (3, 77, [77], None), (4, 38, [2], None)], "run long, source long, targets array<long>, radius long")
    show = lambda df: sorted((r.run, r.target, r.cost, r.path) for r in df.collect())
    assert show(search._frontier_paths(edges, runs, nodes)) == show(search.paths(edges, runs))


def test_rounds_are_as_many_as_blocks(spark, monkeypatch):
    rows = [(k, k + 1, 5) for k in range(60)]
    edges, nodes = spark.createDataFrame(rows, "src long, dst long, weight long"), spark.createDataFrame([(k, float(k), 0.0) for k in range(61)], "node long, x double, y double")
    runs = spark.createDataFrame([(0, 0, [60], None)], "run long, source long, targets array<long>, radius long")
    cuts, cut_size = [], search.cut_size
    monkeypatch.setattr(search, "cut_size", lambda df: cuts.append(df) or cut_size(df))
    found = search._frontier_reach(edges, runs, runs.selectExpr("run", "explode(targets) AS target"), nodes, history=False)
    assert found.where("node = 60").first().dist == 300 and len(cuts) < 10


@pytest.mark.parametrize("few", [1, 9])
def test_fringe_equals_single_searches(few):
    """Random arcs, a lattice with holes, nodes apart from the rest; any nodes may be kept."""
    rng = np.random.default_rng(few)
    for n, leaf in ((2, 4), (30, 4), (144, 8), (144, 300)):
        src, dst = rng.integers(0, n, 3 * n), rng.integers(0, n, 3 * n)
        if n == 144:
            src = np.repeat(np.arange(n), 4)
            dst = src + np.tile([1, -1, 12, -12], n)
        ok = (rng.random(len(src)) < 0.8) & (dst >= 0) & (dst < n) & (src != dst)
        src, dst = src[ok] * 7 + 5, dst[ok] * 7 + 5
        weight = rng.integers(1, few + 1, len(src))
        for kept in (np.arange(0, n, 5), np.arange(n), np.array([0, n + 3])):
            kept = kept * 7 + 5
            table, net = separators.fringe(src, dst, weight, kept, leaf), search.Network(src, dst, weight)
            for i, s in enumerate(kept):
                dist = search.bounded(net, int(s)).dist
                assert [dist.get(int(t), separators.Closed.FAR) for t in kept] == np.minimum(table[i], separators.Closed.FAR).tolist()
    assert separators.fringe(src, dst, weight << 40, kept) is None


def test_overlay_takes_inner_nodes_out(spark, monkeypatch):
    """With very many shared nodes a tile starts no search at each of them."""
    edges, _, rows = network(spark, 8)
    tiled = spark.createDataFrame([(a % 3, a, b, w) for a, b, w in rows], "tile long, src long, dst long, weight long")
    show = lambda df: sorted((r.tile, s, g, int(w)) for r in df.collect() for a, b, c in [overlay._unpacked(r.starts, r.goals, r.ways)] for s, row in zip(a.tolist(), c) for g, w in zip(b.tolist(), row))  # noqa: B905, E731
    want = show(overlay.build(tiled))
    monkeypatch.setattr(overlay, "SINGLE", 0)
    monkeypatch.setattr(search.Indexed, "distances", None)
    assert show(overlay.build(tiled)) == want
