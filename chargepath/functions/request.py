"""JSON requests: {"source": 0, "target": 9, "capacity": ..., "penalty": ..., "n": ..., "aggregate_output": false}."""

from __future__ import annotations

import json
from dataclasses import fields

from pyspark.sql import DataFrame

from chargepath.config import TripOptions
from chargepath.operators.planner import Net, aggregated, plan_trips


def parse(text: str) -> tuple[list[tuple[int, int, int]], TripOptions, bool]:
    """(trips, options, aggregate) of a request; unknown options are an error."""
    body = json.loads(text)
    trips = [(k, int(t["source"]), int(t["target"])) for k, t in enumerate(body.pop("trips", None) or [{"source": body.pop("source"), "target": body.pop("target")}])]
    whole = bool(body.pop("aggregate_output", False))
    known = {f.name for f in fields(TripOptions)}
    if unknown := set(body) - known:
        raise ValueError(f"unknown options: {sorted(unknown)}")
    return trips, TripOptions(**body), whole


def handle(net: Net, text: str) -> DataFrame:
    trips, opts, whole = parse(text)
    plan = plan_trips(net, net.edges.sparkSession.createDataFrame(trips, "trip long, source long, target long"), opts)
    return aggregated(plan.solution) if whole else plan.solution
