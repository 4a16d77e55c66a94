"""Shared plumbing of the corpus operators: durable tables, grouped Arrow streams, word rules."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import discard, ship_package  # noqa: F401
from ..session import durable as materialize  # noqa: F401

#: Words are runs of anything but these ASCII blanks; ``bytes.split()`` splits at exactly them.
BLANKS = r"[\x20\x09-\x0D]+"


def map_arrow(df: DataFrame, work, schema: str) -> DataFrame:
    """``mapInArrow`` with this package on every executor."""
    ship_package(df.sparkSession)
    return df.mapInArrow(work, schema)


def text_column(df: DataFrame, name: str = "text"):
    """Null text counts as empty everywhere."""
    return F.coalesce(df[name].cast("string"), F.lit(""))


def runs(batches, key: str):
    """Groups of equal ``key`` from a stream of Arrow batches that is sorted by it, as tables.

    Only for keys whose groups are bounded by the caller; a group is held whole.
    """
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(batch.schema.get_field_index(key)).to_numpy(zero_copy_only=False)
        cuts = np.flatnonzero(keys[1:] != keys[:-1]) + 1
        edges = [0, *cuts.tolist(), len(keys)]
        for a, b in zip(edges[:-1], edges[1:]):
            if held and keys[a] != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = keys[a]
    if held:
        yield pa.Table.from_batches(held)


def partitions_for(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


class TwoAgeCache:
    """A dictionary of bounded size: when ``now`` is full, it becomes the older half, of which only entries in use are moved up."""

    def __init__(self, limit: int):
        self.limit = limit
        self.now: dict = {}
        self.old: dict = {}

    def missing(self, keys: set) -> list:
        """Keys that must be computed and put into ``now``."""
        if len(self.now) > self.limit:
            self.now, self.old = {}, self.now
        absent = []
        for k in keys.difference(self.now):
            v = self.old.get(k)
            if v is None:
                absent.append(k)
            else:
                self.now[k] = v
        return absent
