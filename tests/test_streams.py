"""Streams over files that come one after the other, with late rows."""

import datetime as dt
import random

import pytest
from pyspark.sql import functions as F

from chargepath.config import TripOptions
from chargepath.operators import planner
from chargepath.plans import queries
from chargepath.streaming import requests, stations, traffic
from tests.test_planner import line

SMALL = "/root/testdata/sf0.001"


def stream_of(spark, df, folder, parts):
    """df as a stream of files, one a batch."""
    for k in range(parts):
        df.where(F.pmod(F.col("event_id"), F.lit(parts)) == k).coalesce(1).write.mode("append").parquet(f"{folder}/in")
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")


def test_linked_lists_in_constant_time():
    store, plain, rng = stations.LinkStore(), {0: [], 1: []}, random.Random(4)
    for _ in range(3000):
        item = rng.randrange(40)
        b = item % 2
        if rng.random() < 0.6:
            assert store.insert(b, item) == (item not in plain[b])
            if item not in plain[b]:
                plain[b].insert(0, item)
        else:
            assert store.remove(b, item) == (item in plain[b])
            if item in plain[b]:
                plain[b].remove(item)
        for k in plain:
            assert list(store.walk(k)) == plain[k]
    assert set(store.links) == {*plain[0], *plain[1]}


def test_bin_lists_over_batches(spark, tmp_path):
    rng, t0 = random.Random(2), dt.datetime(2024, 1, 1)
    rows = [(k, t0 + dt.timedelta(minutes=k), k % 3, rng.randrange(5) * 3 + k % 3, rng.choice(["open", "open", "close"])) for k in range(120)]
    df = spark.createDataFrame(rows, "event_id long, ts timestamp, bin long, station long, op string")
    for k in range(4):  # in order, thirty a file
        df.where(f"event_id DIV 30 = {k}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    key, before = "spark.sql.streaming.stateStore.providerClass", spark.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    spark.conf.set(key, stations.ROCKS)
    try:
        source = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(str(tmp_path / "in"))
        last = {}

        def keep(batch, number):
            found = {}
            for r in batch.collect():
                found.setdefault(r.bin, {})[r.item] = (r.prev, r.next)
            last.update(found)

        requests.run_now(stations.bin_lists(source), str(tmp_path), "update", keep)
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)
    store = stations.LinkStore()
    for _, _, b, item, op in rows:
        (store.insert if op == "open" else store.remove)(b, item)
    for b, links in last.items():
        assert {i: ends for i, ends in store.links.items() if i % 3 == b} == links


def test_windows_of_a_stream_equal_those_of_the_table(spark, tmp_path):
    events = spark.read.parquet(f"{SMALL}/events.parquet")
    rows = traffic.probes(events, 150)
    requests.run_now(traffic.traffic_windows(traffic.probes(stream_of(spark, events, str(tmp_path), 5), 150)), str(tmp_path), "complete")
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "out")).collect())) == sorted(map(tuple, traffic.traffic_windows(rows).collect()))


def test_sessions_and_repeats_of_a_stream(spark, tmp_path):
    events = spark.read.parquet(f"{SMALL}/events.parquet")
    requests.run_now(traffic.request_sessions(stream_of(spark, events, str(tmp_path / "a"), 2)), str(tmp_path / "a"), "complete")
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "a/out")).collect())) == sorted(map(tuple, traffic.request_sessions(events).collect()))
    twice = spark.createDataFrame([(k, dt.datetime(2024, 1, 1, 0, k), 5, 9) for k in range(6)] + [(6, dt.datetime(2024, 1, 1, 0, 6), 5, 8)], "event_id long, ts timestamp, source long, target long")
    requests.run_now(requests.without_repeats(stream_of(spark, twice, str(tmp_path / "b"), 3)), str(tmp_path / "b"))
    assert sorted((r.source, r.target) for r in spark.read.parquet(str(tmp_path / "b/out")).collect()) == [(5, 8), (5, 9)]
    assert requests.without_repeats(twice).count() == 2


def test_outages_before_a_request(spark, tmp_path):
    t = lambda m: dt.datetime(2024, 1, 1, 5, m)
    asked = spark.createDataFrame([(1, t(10), 7, 1), (2, t(40), 7, 2), (3, t(10), 8, 3)], "trip long, ts timestamp, station long, event_id long")
    closed = spark.createDataFrame([(10, t(5), 7, "close"), (11, t(20), 7, "close"), (12, t(9), 8, "open")], "event_id long, ts timestamp, station long, op string")
    want = sorted(map(tuple, requests.outages_near(asked, closed, "30 minutes").select("trip", "event_id").collect()))
    assert want == [(1, 10), (2, 11)]
    a, b = stream_of(spark, asked, str(tmp_path / "a"), 2), stream_of(spark, closed, str(tmp_path / "b"), 2)
    requests.run_now(requests.outages_near(a, b, "30 minutes"), str(tmp_path))
    assert sorted((r.trip, r.event_id) for r in spark.read.parquet(str(tmp_path / "out")).collect()) == want


def test_requests_planned_in_batches(spark, tmp_path):
    net = line(spark)
    bodies = spark.createDataFrame([(k, body) for k, body in enumerate(['{"trip": 1, "source": 0, "target": 10}', "no json", '{"trip": 2, "source": 10, "target": 0}', '{"trip": 2, "source": 10, "target": 0}', '{"source": 3}'])], "event_id long, body string")
    asked = requests.parse_requests(stream_of(spark, bodies, str(tmp_path), 2))
    opts = TripOptions(capacity=50, n=2, penalty=25)
    save = requests.upsert_parquet(str(tmp_path / "plans"), ["trip"])
    requests.run_now(asked, str(tmp_path), "append", requests.planned_in_batches(net, opts, lambda rows, n: save(planner.aggregated(rows).select("trip", "cost"), n)))
    assert dict(requests.read_upserted(spark, str(tmp_path / "plans")).collect()) == {1: 100, 2: 100}
    plan = planner.plan_trips(net, spark.createDataFrame([(1, 0, 10)], "trip long, source long, target long"), opts)
    assert '"cost":100' in requests.answers(plan.solution).first().body


def test_upserts_that_run_again_change_nothing(spark, tmp_path):
    save = requests.upsert_parquet(str(tmp_path / "t"), ["k"])
    rows = lambda *r: spark.createDataFrame(list(r), "k long, v string")
    save(rows((1, "a"), (2, "b")), 0)
    for _ in range(2):
        save(rows((2, "c"), (3, "d")), 1)
    assert sorted(map(tuple, requests.read_upserted(spark, str(tmp_path / "t")).collect())) == [(1, "a"), (2, "c"), (3, "d")]


@pytest.mark.parametrize("name", ["stream_traffic", "stream_dedupe", "stream_outages"])
def test_stream_queries_run(spark, name):
    assert queries.QUERIES[name](spark, SMALL).count() > 0
