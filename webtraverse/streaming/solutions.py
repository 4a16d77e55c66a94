"""Solutions from a stream of matching triples, emitted as soon as their last ingredient arrives.

``pairs`` is a stream-stream join for two patterns: both sides are kept and probed, as a symmetric hash join does. ``network`` takes any number of
patterns: rows meet by a key that all solutions share, and a stateful operator keeps, for each pattern, what has arrived; a new match
is joined with older ones only, so each solution comes once, in whatever order matches arrive.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.query import ConjunctiveQuery
from ..session import ship_package


def pairs(stream: DataFrame, query: ConjunctiveQuery, watermark: str = "1 hour") -> DataFrame:
    """For two patterns; ``stream`` is (arrival, pattern_id, doc, variables...)."""
    if query.n != 2:
        raise ValueError("for two patterns; take network for more")
    sides = []
    for i in (0, 1):
        own = list(query.patterns[i].places())
        sides.append(stream.where(F.col("pattern_id") == i).withWatermark("arrival", watermark).select(*own, F.col("doc").alias(f"d{i}"), F.col("arrival").alias(f"arrival{i}")))
    shared = sorted(set(query.patterns[0].places()) & set(query.patterns[1].places()))
    out = sides[0].join(sides[1], shared)
    return out.select(*query.variables, "d0", "d1", F.greatest("arrival0", "arrival1").alias("t_avail"))


def join_key(query: ConjunctiveQuery) -> list[str]:
    """Variables that every pattern has: solutions never cross their values. Without any, all matches meet in one group."""
    common = set(query.variables)
    for t in query.patterns:
        common &= set(t.places())
    return sorted(common)


def network(stream: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    """(variables..., d0.., rank) for any number of patterns; ``stream`` is (rank, pattern_id, doc, variables...)."""
    ship_package(stream.sparkSession)
    names, n = query.variables, query.n
    docs = [f"d{i}" for i in range(n)]
    own = [[names.index(v) for v in t.places()] for t in query.patterns]
    order = {i: query.join_order(i) for i in range(n)}
    out_cols = [*names, *docs, "rank"]
    schema = ", ".join(f"{c} long" for c in out_cols)

    def advance(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        kept: list[list[tuple]] = [[] for _ in range(n)]
        if state.exists:
            for i, rank, doc, *values in zip(*[list(x) for x in state.get]):
                kept[i].append((tuple(None if v == -(1 << 63) else v for v in values), doc, rank))
        found = []
        for frame in frames:
            for row in frame.sort_values("rank").itertuples(index=False):
                i = int(row.pattern_id)
                values = tuple(None if pd.isna(v) else int(v) for v in (getattr(row, c) for c in names))
                partial = [(values, {i: (int(row.doc), int(row.rank))})]
                for j in order[i][1:]:
                    partial = [
                        (tuple(a if a is not None else b for a, b in zip(v, w)), where | {j: (doc, rank)})
                        for v, where in partial for w, doc, rank in kept[j] if all(v[k] is None or v[k] == w[k] for k in own[j])
                    ]
                found += [(*v, *[w[k][0] for k in range(n)], max(r for _, r in w.values())) for v, w in partial]
                kept[i].append((values, int(row.doc), int(row.rank)))
        flat = [(i, rank, doc, *[-(1 << 63) if v is None else v for v in values]) for i in range(n) for values, doc, rank in kept[i]]
        state.update(tuple([r[c] for r in flat] for c in range(3 + len(names))))
        yield pd.DataFrame(found, columns=out_cols)

    state_schema = "pattern array<long>, ranks array<long>, docs array<long>, " + ", ".join(f"v{i} array<long>" for i in range(len(names)))
    key = join_key(query)
    grouped = stream.select("rank", "pattern_id", "doc", *names).withColumn("_key", F.xxhash64(*key) if key else F.lit(0).cast("long")).groupBy("_key")
    return grouped.applyInPandasWithState(advance, schema, state_schema, "append", GroupStateTimeout.NoTimeout)
