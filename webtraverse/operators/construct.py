"""From matching triples to solutions.

``solutions`` joins all matches at once; Catalyst and AQE choose the physical joins. A solution exists as soon as its last ingredient is
there, so its time is the greatest rank among its documents: the whole timeline of a given order follows without iteration.
``delta`` adds the solutions whose newest ingredient belongs to the current batch. ``hops`` sends partials from
operator to operator, one by one, as a routing policy says.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.query import ConjunctiveQuery
from ..session import durable
from .routing import Routing


def pattern_frame(found: DataFrame, query: ConjunctiveQuery, i: int, *carry: str) -> DataFrame:
    """Matches of pattern ``i``: its variables, its document as ``d{i}``, and carried columns as ``{name}{i}``."""
    own = list(query.patterns[i].places())
    return found.where(F.col("pattern_id") == i).select(*own, F.col("doc").alias(f"d{i}"), *[F.col(c).alias(f"{c}{i}") for c in carry])


def join_all(frames: list[DataFrame], query: ConjunctiveQuery, order: list[int]) -> DataFrame:
    """Natural joins in the given order; patterns without a shared variable are paired in full, as their definition asks."""
    out, known = frames[order[0]], set(query.patterns[order[0]].places())
    for i in order[1:]:
        own = set(query.patterns[i].places())
        shared = sorted(known & own)
        out = out.join(frames[i], shared) if shared else out.crossJoin(frames[i])
        known |= own
    return out


def solutions(found: DataFrame, query: ConjunctiveQuery, *carry: str) -> DataFrame:
    """Bag solutions: the variables, the document of each ingredient, and the provenance."""
    frames = [pattern_frame(found, query, i, *carry) for i in range(query.n)]
    out = join_all(frames, query, query.join_order())
    docs = [F.col(f"d{i}") for i in range(query.n)]
    carried = [f"{c}{i}" for c in carry for i in range(query.n)]
    return out.select(*query.variables, *docs, *carried, F.array_distinct(F.array(*docs)).alias("prov"))


def distinct_matches(found: DataFrame, by: str = "doc") -> DataFrame:
    """Set semantics: of equal matching triples only the one that came first, by ``by``, is indexed."""
    rest = [c for c in found.columns if c not in ("doc", "pattern_id", "_s", "_p", "_o")]
    kept = found.groupBy("pattern_id", "_s", "_p", "_o").agg(F.min_by(F.struct("doc", *rest), F.struct(by, "doc")).alias("m"))
    return kept.select("pattern_id", "_s", "_p", "_o", "m.*").select(*found.columns)


def offline(found: DataFrame, trace: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    """Solutions with ``t_avail``, for any given order of lookups ``trace`` (doc, rank)."""
    timed = found.join(trace.select("doc", "rank"), "doc")
    out = solutions(timed, query, "rank")
    ranks = [F.col(f"rank{i}") for i in range(query.n)]
    return out.withColumn("t_avail", F.greatest(*ranks) if query.n > 1 else ranks[0]).drop(*[f"rank{i}" for i in range(query.n)])


def bag_count(found: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    """One row: the number of bag and set solutions, from matches with multiplicities, so that copies are never expanded."""
    frames = []
    for i in range(query.n):
        own = list(query.patterns[i].places())
        frames.append(found.where(F.col("pattern_id") == i).groupBy(*own).agg(F.count("*").alias(f"n{i}")))
    joined = join_all(frames, query, query.join_order())
    product = reduce(lambda a, b: a * b, [F.col(f"n{i}") for i in range(query.n)])
    return joined.agg(F.coalesce(F.sum(product), F.lit(0)).alias("n_bag"), F.count("*").alias("n_set"))


def full_web(triples: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    """Evaluation over the whole web as one graph, the way of a warehouse: triples are a set, reachability plays no part."""
    from .reach import matches

    unique = triples.dropDuplicates(["s", "p", "o"])
    return solutions(matches(unique, query), query).select(*query.variables)


def delta(new: DataFrame, old: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    """Solutions with at least one new ingredient: for each pattern i, its new matches with old ones of later patterns and all of earlier ones."""
    both = old.unionByName(new)
    out = None
    for i in range(query.n):
        frames = [pattern_frame(new if j == i else both if j < i else old, query, j) for j in range(query.n)]
        part = join_all(frames, query, query.join_order(i))
        docs = [F.col(f"d{j}") for j in range(query.n)]
        part = part.select(*query.variables, *docs, F.array_distinct(F.array(*docs)).alias("prov"))
        out = part if out is None else out.unionByName(part)
    return out


def stamped(found: DataFrame, trace: DataFrame) -> DataFrame:
    """Matches with a unique, total timestamp: the rank of the lookup, then the place of the triple in its document, then the pattern."""
    timed = found.join(trace.select("doc", "rank"), "doc")
    place = F.row_number().over(W.partitionBy("doc").orderBy("_s", "_p", "_o", "pattern_id"))
    return timed.withColumn("ts", F.shiftleft(F.col("rank").cast("long"), 24) + place)


def asof_sizes(ts_frame: DataFrame, query: ConjunctiveQuery, bucket: int = 4096) -> DataFrame:
    """``sizes``: how many matches each operator had indexed before each match. Prefix sums in two levels: buckets of ranks, then rows of a bucket."""
    zone = F.floor(F.col("rank") / bucket).cast("long")
    own = [(F.col("pattern_id") == i).cast("long") for i in range(query.n)]
    rows = ts_frame.withColumn("zone", zone)
    totals = rows.groupBy("zone").agg(*[F.sum(c).alias(f"c{i}") for i, c in enumerate(own)])
    earlier = W.orderBy("zone").rowsBetween(W.unboundedPreceding, -1)
    before = totals.select("zone", *[F.coalesce(F.sum(f"c{i}").over(earlier), F.lit(0)).alias(f"b{i}") for i in range(query.n)])
    inside = W.partitionBy("zone").orderBy("ts").rowsBetween(W.unboundedPreceding, -1)
    return rows.join(before, "zone").withColumn("sizes", F.array(*[F.col(f"b{i}") + F.coalesce(F.sum(own[i]).over(inside), F.lit(0)) for i in range(query.n)])).drop("zone", *[f"b{i}" for i in range(query.n)])


def hops(initial: DataFrame, index: DataFrame, query: ConjunctiveQuery, routing: Routing = Routing(), history: dict | None = None) -> tuple[DataFrame, list[DataFrame]]:
    """Solutions (variables, d0.., ts) and, for each hop, the partials that were routed (variables, covered, ts, target).

    ``initial`` are stamped matches with sizes, which drive; ``index`` are stamped matches to probe; partners are strictly older.
    """
    names = query.variables
    docs = [f"d{i}" for i in range(query.n)]
    own_doc = [F.when(F.col("pattern_id") == i, F.col("doc")).alias(f"d{i}") for i in range(query.n)]
    now = initial.select(*names, "ts", "sizes", F.expr("shiftleft(1, pattern_id)").alias("covered"), *own_doc)
    masks, routed, full = {1 << i for i in range(query.n)}, [], (1 << query.n) - 1
    for _ in range(query.n - 1):
        target = F.lit(None).cast("int")
        for mask in sorted(masks):
            target = F.when(F.col("covered") == mask, routing.column(query, mask, history)).otherwise(target)
        now = durable(now.withColumn("target", target), "hop")
        routed.append(now)
        parts, following = [], set()
        for mask in sorted(masks):
            for i in routing.fixed_choice(query, mask):
                shared = sorted(query.variables_of(mask) & set(query.patterns[i].places()))
                fresh = sorted(set(query.patterns[i].places()) - set(shared))
                partner = index.where(F.col("pattern_id") == i).select(*[F.col(v).alias(f"_{v}") for v in query.patterns[i].places()], F.col("ts").alias("_ts"), F.col("doc").alias("_doc"))
                on = [F.col(v) == F.col(f"_{v}") for v in shared] + [F.col("_ts") < F.col("ts")]
                left = now.where((F.col("covered") == mask) & (F.col("target") == i))
                met = left.join(partner, on)
                parts.append(
                    met.select(
                        *[F.col(f"_{v}").alias(v) if v in fresh else F.col(v) for v in names], "ts", "sizes", F.lit(mask | 1 << i).alias("covered"), *[F.col("_doc").alias(d) if d == f"d{i}" else F.col(d) for d in docs]
                    )
                )
                following.add(mask | 1 << i)
        now = reduce(DataFrame.unionByName, parts)
        masks = following
    return now.where(F.col("covered") == full).select(*names, *docs, "ts"), routed


def routed_stats(routed: list[DataFrame]) -> DataFrame:
    """(hop, n_routed): how many partials the dispatcher handled at each hop."""
    return reduce(DataFrame.unionByName, [r.agg(F.lit(i + 1).alias("hop"), F.count("*").alias("n_routed")) for i, r in enumerate(routed)])
