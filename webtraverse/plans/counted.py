"""What plans route under first come, first served, counted in tables of any size.

There the order of lookups follows from the web alone, and with it the order of matches; which operator a partial goes to changes neither.
With three patterns a partial has a choice once, when it covers one pattern, so each match makes one choice: by index sizes before it, or by
the draw of its place. It meets the older matches of that operator with equal shared variables; they are counted, not paired.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations
from random import Random

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.terms import LITERAL, URI
from ..operators import construct, metrics
from ..operators.reach import matches, ranked, seed_frame
from ..operators.routing import Routing
from ..session import discard, durable, ship_package
from .approaches import Approach, Arrival
from .query import ConjunctiveQuery, Lit
from .rounds import _all, _fold

#: Draws that are made at a time, a multiple of 64.
CHUNK = 1 << 20


def countable(query: ConjunctiveQuery, approach: Approach, routing: Routing) -> bool:
    """Whether ``count`` knows this plan: its choices rest on the matches before, not on what earlier partials met."""
    if query.n > 3 or not isinstance(approach, Arrival) or approach.step or approach.draw or any(isinstance(x, Lit) for t in query.patterns for x in (t.s, t.p, t.o)):
        return False
    free = query.n == 3 and any(len(routing.fixed_choice(query, 1 << i)) > 1 for i in range(query.n))
    return not free or (not {"ls", "ms"} & set(routing.rules) and (routing.seed is None or not routing.rules))


def arrival_order(said: DataFrame, docs: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    """(doc, rank) from ``said`` (src, at, dst): what of ``docs`` a document mentions, in its order. URIs found in a round come after all that were queued."""
    spark, seen, n = said.sparkSession, [], 0
    new = durable(seed_frame(spark, query).select(F.col("uri").alias("doc"), F.col("seed_no").alias("o")).join(docs, "doc", "left_semi"), "new")
    while not new.isEmpty():
        last = durable(ranked(new, "o").select("doc", (F.col("rank") + n).cast("long").alias("rank")), "order")
        discard(new)
        n += last.count()
        seen.append(last)
        firsts = said.join(last.select(F.col("doc").alias("src"), "rank"), "src").groupBy(F.col("dst").alias("doc")).agg(F.min(F.struct("rank", "at")).alias("o"))
        new = durable(firsts.join(_all(seen).select("doc"), "doc", "left_anti"), "new")
        _fold(seen, "order")
    discard(new)
    return _all(seen) if seen else spark.createDataFrame([], "doc long, rank long")


def draws(spark: SparkSession, seed: int, n: int) -> DataFrame:
    """(word, bits): the first ``n`` values of ``Random(seed).randrange(2)`` or some more, 64 in a row, the first one lowest."""
    ship_package(spark)
    return spark.range(0, 1, 1, 1).mapInPandas(lambda _: _drawn(seed, n), "word long, bits long")


def _drawn(seed: int, n: int):
    """A draw is the two highest bits of the next number, taken again while they are no draw; numpy holds the same generator."""
    *key, pos = Random(seed).getstate()[1]
    source, held = np.random.MT19937(), np.zeros(0, bool)
    source.state = {"bit_generator": "MT19937", "state": {"key": np.array(key, np.uint32), "pos": pos}}
    for first in range(0, n, CHUNK):
        while len(held) < CHUNK:
            top = source.random_raw(2 * CHUNK) >> np.uint64(30)
            held = np.concatenate([held, top[top < 2].astype(bool)])
        yield pd.DataFrame({"word": np.arange(first // 64, (first + CHUNK) // 64), "bits": np.packbits(held[:CHUNK], bitorder="little").view("<i8")})
        held = held[CHUNK:]


def _target(query: ConjunctiveQuery, routing: Routing, drawn: str | None) -> Column:
    """The operator to which a match's first partial is sent."""
    out = F.lit(None).cast("int")
    for i in range(query.n):
        among = routing.fixed_choice(query, 1 << i)
        choice = routing.column(query, 1 << i) if drawn is None or len(among) == 1 else F.when(F.col(drawn) == 0, among[0]).otherwise(among[1])
        out = F.when(F.col("pattern_id") == i, choice).otherwise(out)
    return out


def count(triples: DataFrame, reached: DataFrame, query: ConjunctiveQuery, routings: list[Routing]) -> dict:
    """Counts and times of the execution over ``triples`` (doc, s, p, o) of ``reached`` (doc); ``routed`` has a number for each of ``routings``."""
    spark = triples.sparkSession
    docs = reached.select("doc").distinct()
    held = triples.where("s is not null").select("doc", "s", "p", "o", F.when(F.col("o") >= 0, URI).otherwise(LITERAL).alias("o_kind")).join(docs, "doc", "left_semi")
    # The place of a match in its document, as ``construct.stamped`` gives it.
    place = F.row_number().over(W.partitionBy("doc").orderBy("_s", "_p", "_o", "pattern_id"))
    found = durable(matches(held, query).withColumn("place", place.cast("long")), "matches")
    uris = F.posexplode(F.array("_s", F.col("_p").cast("long") * 16, "_o")).alias("pos", "dst")
    uses = found.select(F.col("doc").alias("src"), "place", uris).where("dst >= 0").groupBy("src", "dst").agg(F.min(F.col("place") * 3 + F.col("pos")).alias("at"))
    uses = durable(uses, "uses")
    # Links that lead nowhere are left out once, so that no round looks at all names.
    said = durable(uses.where("src <> dst").join(docs.select(F.col("doc").alias("dst")), "dst", "left_semi").select("src", "at", "dst"), "said")
    trace = durable(arrival_order(said, docs, query), "trace")
    n_docs = trace.count()
    known = uses.join(trace.select(F.col("doc").alias("src")), "src", "left_semi").select(F.col("dst").alias("uri")).unionByName(seed_frame(spark, query).select("uri"))
    stamped = found.join(trace, "doc").select("pattern_id", "doc", *query.variables, "rank", (F.shiftleft("rank", 24) + F.col("place")).alias("ts"))
    stamped = durable(stamped, "stamped")
    ranks = [F.col(f"rank{i}") for i in range(query.n)]
    solved = construct.solutions(stamped, query, "rank").select((F.greatest(*ranks) if query.n > 1 else ranks[0]).alias("t_avail"))
    times = metrics.response_times(solved, n_docs).first()
    n = stamped.count()
    return {
        "n_docs": n_docs,
        "attempted": known.distinct().count(),
        "n_solutions": times["n_solutions"] if times else 0,
        **{t: times[t] if times else None for t in ("t_first", "t_half", "t_last", "relRT1st", "relRT50", "relRTCmpl")},
        "routed": [n + more for more in _met(stamped, query, routings, n)] if query.n > 1 else [0] * len(routings),
    }


def _met(stamped: DataFrame, query: ConjunctiveQuery, routings: list[Routing], n: int) -> list[int]:
    """How many older matches the first partials meet under each routing; the partials of both are routed once more."""
    if query.n < 3:
        return [0] * len(routings)
    rows = construct.asof_sizes(stamped, query)
    before = reduce(Column.__add__, [F.col("sizes")[i] for i in range(query.n)])
    rows = durable(rows.select("pattern_id", *query.variables, "ts", "sizes", before.alias("before")), "sized")
    seeds = sorted({r.seed for r in routings if r.seed is not None})
    for seed in seeds:
        some = draws(rows.sparkSession, seed, n)
        rows = rows.withColumn("word", F.shiftright("before", 6)).join(some, "word").withColumn(f"draw{seed}", F.expr("shiftright(bits, cast(before & 63 as int)) & 1")).drop("word", "bits")
    if seeds:
        rows = durable(rows, "drawn")
    sums = []
    for a, b in combinations(range(query.n), 2):
        here, first = rows.where(F.col("pattern_id").isin(a, b)), F.col("pattern_id") == a
        shared = sorted(query.variables_of(1 << a) & query.variables_of(1 << b))
        if shared:
            earlier = W.partitionBy(*shared).orderBy("ts").rowsBetween(W.unboundedPreceding, -1)
            older = F.when(first, F.count_if(~first).over(earlier)).otherwise(F.count_if(first).over(earlier))
        else:
            older = F.when(first, F.col("sizes")[b]).otherwise(F.col("sizes")[a])
        here = here.withColumn("older", older).withColumn("other", F.when(first, b).otherwise(a))
        routes = [_target(query, r, None if r.seed is None else f"draw{r.seed}") == F.col("other") for r in routings]
        sums.append(here.agg(*[F.coalesce(F.sum(F.when(to, F.col("older"))), F.lit(0)).alias(f"r{k}") for k, to in enumerate(routes)]))
    got = [row for s in sums for row in s.collect()]
    return [sum(row[k] for row in got) for k in range(len(routings))]
