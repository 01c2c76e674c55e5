"""The lookup that motivates vectors of records: a hash join by Spark, by vectors of keys, and key by key."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A table to probe is broadcast; it may have no more rows than this.
MAX_BUILD = 4_000_000


class Table:
    """Open addressing with linear probing, at most half full."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.log = max(1, int(2 * len(keys)).bit_length())
        self.mask = (1 << self.log) - 1
        self.used = np.zeros(1 << self.log, bool)
        self.keys, self.values = np.zeros(1 << self.log, np.int64), np.zeros(1 << self.log, np.int64)
        todo = np.arange(len(keys))
        slot = self.slot(keys)
        while len(todo):  # one of those that want a free slot gets it, the rest move on
            free = ~self.used[slot]
            win = np.zeros(len(todo), bool)
            if free.any():
                _, first = np.unique(slot[free], return_index=True)
                win[np.flatnonzero(free)[first]] = True
            s = slot[win]
            self.used[s], self.keys[s], self.values[s] = True, keys[todo[win]], values[todo[win]]
            todo, slot = todo[~win], slot[~win] + 1 & self.mask

    def slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.log)).astype(np.int64)


def vectorised(keys: np.ndarray, table: Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(positions that hit, their values, positions that miss): all active positions take a step together."""
    active, slot = np.arange(len(keys)), table.slot(keys)
    hits, found, misses = [], [], []
    while len(active):
        used, same = table.used[slot], table.keys[slot] == keys[active]
        hit = used & same
        hits.append(active[hit])
        found.append(table.values[slot[hit]])
        misses.append(active[~used])
        go = used & ~same
        active, slot = active[go], slot[go] + 1 & table.mask
    cat = lambda x: np.concatenate(x) if x else np.zeros(0, np.int64)
    return cat(hits), cat(found), cat(misses)


def scalar(keys: np.ndarray, table: Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    hits, found, misses = [], [], []
    for i, k in enumerate(keys.tolist()):
        s = int(table.slot(np.array([k]))[0])
        while table.used[s] and table.keys[s] != k:
            s = s + 1 & table.mask
        if table.used[s]:
            hits.append(i)
            found.append(int(table.values[s]))
        else:
            misses.append(i)
    return np.array(hits, np.int64), np.array(found, np.int64), np.array(misses, np.int64)


def probe(left: DataFrame, right: DataFrame, key: str, value: str, how=vectorised) -> DataFrame:
    """left with `found` (null where nothing is): right(key unique, value) is shipped to each worker after a check of its size."""
    rows = right.limit(MAX_BUILD + 1).count()
    if rows > MAX_BUILD:
        return left.join(right.select(key, F.col(value).alias("found")), key, "left")
    k, v = (np.array(x, np.int64) for x in zip(*((r[0], r[1]) for r in right.select(key, value).toLocalIterator()), strict=True)) if rows else (np.zeros(0, np.int64),) * 2
    shipped = left.sparkSession.sparkContext.broadcast((k, v))
    names, made = left.columns, {}

    def run(batches):
        if "table" not in made:
            made["table"] = Table(*shipped.value)
        for b in batches:
            keys = b.column(key).to_numpy(zero_copy_only=False).astype(np.int64)
            hit, got, _ = how(keys, made["table"])
            found, none = np.zeros(len(keys), np.int64), np.ones(len(keys), bool)
            found[hit], none[hit] = got, False
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(found, mask=none)], names=[*names, "found"])

    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in left.schema.fields), "found long"])
    return left.mapInArrow(run, ddl)
