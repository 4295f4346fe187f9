"""Stations that open and close on a stream: the linked lists of the bins, kept in state."""

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
LINKS = "bin long, item long, prev long, next long"


class LinkStore:
    """Doubly linked lists of bins over any mapping: item -> (prev, next), and the head of each bin.

    Insertion puts an item at the head, removal joins its neighbours; both touch
    a constant number of entries.
    """

    def __init__(self, links=None, heads=None) -> None:
        self.links = {} if links is None else links
        self.heads = {} if heads is None else heads

    def insert(self, bin_: int, item: int) -> bool:
        if item in self.links:
            return False
        head = self.heads.get(bin_)
        self.links[item] = (None, head)
        if head is not None:
            self.links[head] = (item, self.links[head][1])
        self.heads[bin_] = item
        return True

    def remove(self, bin_: int, item: int) -> bool:
        if item not in self.links:
            return False
        prev, next_ = self.links.pop(item)
        if prev is None:
            if next_ is None:
                self.heads.pop(bin_, None)
            else:
                self.heads[bin_] = next_
        else:
            self.links[prev] = (self.links[prev][0], next_)
        if next_ is not None:
            self.links[next_] = (prev, self.links[next_][1])
        return True

    def walk(self, bin_: int) -> Iterator[int]:
        at = self.heads.get(bin_)
        while at is not None:
            yield at
            at = self.links[at][1]


class _Items:
    """The mapping that LinkStore asks for, over a map state; an end of a list is -1 there."""

    def __init__(self, state) -> None:
        self.state = state

    def __contains__(self, item: int) -> bool:
        return self.state.containsKey((item,))

    def __getitem__(self, item: int):
        prev, next_ = self.state.getValue((item,))
        return (None if prev < 0 else prev, None if next_ < 0 else next_)

    def __setitem__(self, item: int, ends) -> None:
        self.state.updateValue((item,), tuple(-1 if e is None else e for e in ends))

    def pop(self, item: int):
        ends = self[item]
        self.state.removeKey((item,))
        return ends


class _Head:
    """The head of the one bin of a group."""

    def __init__(self, state) -> None:
        self.state = state

    def get(self, _):
        return self.state.get()[0] if self.state.exists() else None

    def __setitem__(self, _, item: int) -> None:
        self.state.update((item,))

    def pop(self, _, default=None) -> None:
        self.state.clear()


class BinLists(StatefulProcessor):
    """Each bin's list; after a batch it tells the lists of the bins that had changes."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.items = _Items(handle.getMapState("items", "item long", "prev long, next long"))
        self.head = _Head(handle.getValueState("head", "item long"))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        store, bin_ = LinkStore(self.items, self.head), key[0]
        every = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        for op, item in zip(every["op"], every["station"].tolist(), strict=True):
            (store.insert if op == "open" else store.remove)(bin_, item)
        out = [(bin_, i, *self.items[i]) for i in store.walk(bin_)]
        yield pd.DataFrame(out, columns=["bin", "item", "prev", "next"]).astype("Int64")

    def close(self) -> None:
        pass


def bin_lists(changes: DataFrame) -> DataFrame:
    """A stream of changes(ts, event_id, bin, station, op) -> the lists of changed bins after each batch.

    Needs the RocksDB state store (see ``ROCKS``), whose maps are read by key.
    """
    return changes.groupBy("bin").transformWithStateInPandas(BinLists(), LINKS, "Update", "None")


def with_bins(changes: DataFrame, stations: DataFrame) -> DataFrame:
    """Stream-static join: each change with its station's bin."""
    return changes.join(stations.select("station", F.col("bin").cast("long").alias("bin")), "station")
