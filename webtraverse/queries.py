"""Named queries over the given tables, each with its SQL twin where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions.terms import LITERALS, draw_sql, place_draws
from .operators import construct, linkgraph, metrics, reach
from .operators.reach import Web
from .operators.routing import Routing
from .plans import experiments, rounds
from .plans.approaches import APPROACHES, LITERAL_HYBRIDS
from .plans.query import SIX, WORKLOAD, ConjunctiveQuery, TriplePattern, Var, join_sql, pattern_sql, query
from .session import durable
from .sources import basegraph, pages_web, testweb
from .sources.basegraph import ENTITY_SQL, LINK_SQL, literal_sql, table
from .sources.testweb import CORPUS_LIKE, WEBS, web_sql
from .streaming import windows

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

_kept: dict[tuple, object] = {}


def _once(spark: SparkSession, key: tuple, make: Callable):
    """Webs and reachable parts are written once for an application and directory, as webs on disk would be."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]


def web_of(spark: SparkSession, sf_dir: str, literals: bool = False) -> Web:
    def make():
        triples = durable(testweb.build(spark, sf_dir, CORPUS_LIKE, literals), "web")
        return Web(triples, durable(testweb.resolve(spark, sf_dir), "resolve"))

    return _once(spark, ("web", sf_dir, literals), make)


def reached_by(spark: SparkSession, sf_dir: str, name: str, follow: str = "match") -> DataFrame:
    return _once(spark, ("reach", sf_dir, name, follow), lambda: durable(reach.reach(web_of(spark, sf_dir, name == "q7"), WORKLOAD[name], follow), "reached"))


def matches_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Matching triples of reached documents."""
    found = reach.matches(web_of(spark, sf_dir, name == "q7").triples, WORKLOAD[name])
    return found.join(reached_by(spark, sf_dir, name).select("doc"), "doc")


def trace_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return _once(spark, ("trace", sf_dir, name), lambda: durable(reach.canonical_trace(reached_by(spark, sf_dir, name)), "trace"))


def timed(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return construct.offline(matches_of(spark, sf_dir, name), trace_of(spark, sf_dir, name), WORKLOAD[name])


def reached_links(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """All links of reached documents to other entities."""
    web = web_of(spark, sf_dir)
    edges = reach.links(web.triples).join(reached_by(spark, sf_dir, name).select(F.col("doc").alias("src")), "src")
    return edges.join(web.resolve.where("doc is not null").select(F.col("uri").alias("dst")), "dst").select("src", "dst")


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def ctes(name: str, follow: str = "match") -> str:
    return reach_ctes(WORKLOAD[name], follow)


def reach_ctes(q: ConjunctiveQuery, follow: str = "match") -> str:
    return reach.reach_ctes(q, web_sql(), ENTITY_SQL, follow)


def solved(name: str) -> str:
    """CTEs that end in sol (variables, d0.., t) and rcc (doc, rcc) over reached documents."""
    q = WORKLOAD[name]
    ranks = "".join(f" join traced t{i} on t{i}.doc = j.d{i}" for i in range(q.n))
    t = f"greatest({', '.join(f't{i}.rank' for i in range(q.n))})"
    docs = ", ".join(f"d{i}" for i in range(q.n))
    return (
        f"{ctes(name)}, seen as materialized (select web.* from web join reached using (doc)), j as materialized ({join_sql(q, source='seen')}), "
        f"sol as materialized (select j.*, {t} as t, row_number() over () as sol_id from j{ranks}), "
        f"rcc as materialized (select doc, count(*) as rcc from (select distinct sol_id, unnest([{docs}]) as doc from sol) group by 1)"
    )


LINKED = "lk as materialized (select distinct src, dst from (select doc as src, s as dst from seen union all select doc, o from seen) where src <> dst and dst in (select uri from ent))"

# Base graph and webs ------------------------------------------------------------------------------------------------


@register("base_link_triples", LINK_SQL)
def base_link_triples(spark, sf_dir):
    return basegraph.link_triples(spark, sf_dir)


@register("base_literal_triples", literal_sql())
def base_literal_triples(spark, sf_dir):
    return basegraph.literal_triples(spark, sf_dir).select("s", "p", "o_str", "o_dbl", "o_ts")


@register("scan_base_triples", f"select p, count(*)::bigint as n, count(distinct s)::bigint as subjects from ({LINK_SQL}) group by 1")
def scan_base_triples(spark, sf_dir):
    return basegraph.triples(spark, sf_dir, literals=False).groupBy("p").agg(F.count("*").alias("n"), F.countDistinct("s").alias("subjects"))


@register("entity_catalog", ENTITY_SQL)
def entity_catalog(spark, sf_dir):
    return basegraph.entities(spark, sf_dir)


M = 2147483647
DRAWS = f"select s, p, o, (h * 48271 % {M}) / {M} as u1, (h * 69621 % {M}) / {M} as u2 from (select s, p, o, ((s % {M}) * 1000003 + p::bigint * 7919 + (o % {M}) * 31337 + 42 * 101) % {M} as h from ({LINK_SQL}))"


@register("place_draws", f"select s, p, o, round(u1, 9) as u1, round(u2, 9) as u2 from ({DRAWS})")
def place_draws_(spark, sf_dir):
    u1, u2 = place_draws(F.col("s"), F.col("p"), F.col("o"), 42)
    return basegraph.link_triples(spark, sf_dir).select("s", "p", "o", F.round(u1, 9).alias("u1"), F.round(u2, 9).alias("u2"))


ALL_WEBS_SQL = "with d as materialized (" + DRAWS + "), w(web_id, phi1, phi2) as (values " + ", ".join(f"('{w.web_id}', {w.phi1}, {w.phi2})" for w in WEBS) + "), placed as materialized (select web_id, s, p, o, case when u1 < phi1 then 'both' when u2 < phi2 then 'subject' else 'object' end as side from d, w)"


@register("web_link_counts", ALL_WEBS_SQL + " select web_id, side, count(*)::bigint as n from placed group by all")
def web_link_counts(spark, sf_dir):
    webs = testweb.all_webs(basegraph.triples(spark, sf_dir, literals=False)).groupBy("web_id", "s", "p", "o").agg(F.max((F.col("doc") == F.col("s")).cast("int")).alias("a"), F.max((F.col("doc") == F.col("o")).cast("int")).alias("b"))
    return webs.groupBy("web_id", F.when(F.col("a") + F.col("b") == 2, "both").when(F.col("a") == 1, "subject").otherwise("object").alias("side")).agg(F.count("*").alias("n"))


@register("estimate_phi", ALL_WEBS_SQL + " select web_id, round(sum((side = 'both')::int) / count(*), 9) as phi1, round(sum((side = 'subject')::int) / nullif(sum((side <> 'both')::int), 0), 9) as phi2, count(*)::bigint as n_links from placed group by 1")
def estimate_phi(spark, sf_dir):
    got = testweb.estimate_phi(testweb.all_webs(basegraph.triples(spark, sf_dir, literals=False)))
    return got.select("web_id", F.round("phi1", 9).alias("phi1"), F.round("phi2", 9).alias("phi2"), "n_links")


@register("density_rollup", ALL_WEBS_SQL + " select w.phi1 > 0.5 as dense, web_id, count(*)::bigint as n from placed join w using (web_id) group by rollup (w.phi1 > 0.5, web_id)")
def density_rollup(spark, sf_dir):
    links = testweb.all_webs(basegraph.triples(spark, sf_dir, literals=False)).select("web_id", "s", "p", "o").distinct()
    dense = F.col("web_id").isin([w.web_id for w in WEBS if w.dense])
    return links.withColumn("dense", dense).rollup("dense", "web_id").agg(F.count("*").alias("n"))


@register("triples_cube_by_pred_side", ALL_WEBS_SQL + " select p, side, count(*)::bigint as n from placed where web_id = 'w62_47' group by cube (p, side)")
def triples_cube(spark, sf_dir):
    u1, u2 = place_draws(F.col("s"), F.col("p"), F.col("o"), 42)
    side = F.when(u1 < CORPUS_LIKE.phi1, "both").when(u2 < CORPUS_LIKE.phi2, "subject").otherwise("object")
    return basegraph.link_triples(spark, sf_dir).withColumn("side", side).cube("p", "side").agg(F.count("*").alias("n"))


@register("scan_web_partition", web_sql(WEBS[5]))
def scan_web_partition(spark, sf_dir):
    path = _once(spark, ("webs", sf_dir), lambda: _write_webs(spark, sf_dir))
    return spark.read.parquet(path).where(F.col("web_id") == WEBS[5].web_id).select("doc", "s", "p", "o")


def _write_webs(spark, sf_dir):
    from .session import shared_dir
    import uuid

    path = f"{shared_dir(spark)}/webs-{uuid.uuid4().hex}"
    testweb.write_webs(testweb.all_webs(basegraph.triples(spark, sf_dir, literals=False), WEBS[4:7]), path, files_per_web=4)
    return path


def _two(a, b):
    return f"with a as ({web_sql(a)}), b as ({web_sql(b)}) "


SPARSE, DENSE = WEBS[5], WEBS[9]


@register("docs_in_both_webs", _two(SPARSE, DENSE) + "select doc from a intersect select doc from b")
def docs_in_both_webs(spark, sf_dir):
    base = basegraph.triples(spark, sf_dir, literals=False)
    return testweb.place(base, SPARSE).select("doc").intersect(testweb.place(base, DENSE).select("doc"))


@register("docs_only_dense", _two(SPARSE, DENSE) + "select doc from b except select doc from a")
def docs_only_dense(spark, sf_dir):
    base = basegraph.triples(spark, sf_dir, literals=False)
    return testweb.place(base, DENSE).select("doc").subtract(testweb.place(base, SPARSE).select("doc"))


@register("first_doc_per_triple", f"select s, p, o, min(doc) as doc, count(*)::bigint as copies from ({web_sql()}) group by 1, 2, 3")
def first_doc_per_triple(spark, sf_dir):
    return web_of(spark, sf_dir).triples.groupBy("s", "p", "o").agg(F.min("doc").alias("doc"), F.count("*").alias("copies"))


# Matching -----------------------------------------------------------------------------------------------------------


def _match_sql(q: ConjunctiveQuery) -> str:
    parts = []
    for i, t in enumerate(q.patterns):
        own = pattern_sql(t)
        cols = ", ".join(v if v in t.places() else f"null::bigint as {v}" for v in q.variables)
        parts.append(f"select {i} as pattern_id, doc, {cols} from ({own})")
    return f"with web as ({web_sql()}) " + " union all ".join(parts)


for _name in SIX:

    @register(f"match_{_name}", _match_sql(WORKLOAD[_name]))
    def _match(spark, sf_dir, name=_name):
        return reach.matches(web_of(spark, sf_dir).triples, WORKLOAD[name]).select("pattern_id", "doc", *WORKLOAD[name].variables)


ANY = ConjunctiveQuery("any", (TriplePattern(Var("x"), Var("q"), 3 * 16 + 2),))
SELF = ConjunctiveQuery("self", (TriplePattern(Var("x"), Var("q"), Var("x")),))
APART = query("apart", ("?a", "s_nation", "nation:3"), ("?b", "n_name", "FRANCE"))
PAIR = query("pair", ("?a", "c_nation", "nation:3"), ("?b", "in_region", "region:2"))


@register("match_variable_predicate", f"select doc, s as x, p::bigint * 16 as q from ({web_sql()}) where o = 50")
def match_variable_predicate(spark, sf_dir):
    return reach.matches(web_of(spark, sf_dir).triples, ANY).select("doc", "x", "q")


@register("match_repeated_variable", f"select count(*)::bigint as n from ({web_sql()}) where s = o")
def match_repeated_variable(spark, sf_dir):
    return reach.matches(web_of(spark, sf_dir).triples, SELF).agg(F.count("*").alias("n"))


@register("match_literal_constant", f"select s as c, p from ({literal_sql()}) where (p = {LITERALS['c_mktsegment']} and o_str = 'BUILDING') or (p = {LITERALS['p_size']} and o_dbl = 7)")
def match_literal_constant(spark, sf_dir):
    q = query("lit", ("?c", "c_mktsegment", "BUILDING"), ("?c", "p_size", 7.0))
    sized = ConjunctiveQuery("lit", (q.patterns[0], query("x", ("?c", "p_size", 7.0)).patterns[0]))
    return reach.matches(web_of(spark, sf_dir, True).triples, sized).select("c", F.col("_p").alias("p"))


@register("all_match_union", f"with web as ({web_sql()}) select 'q1' as query, count(*)::bigint as n from web where p in (5, 6) or (p = 4 and o = 115) union all select 'q2', count(*)::bigint from web where p = 4 or (p = 2 and o = 50)")
def all_match_union(spark, sf_dir):
    web = web_of(spark, sf_dir).triples
    return reduce(DataFrame.unionByName, [reach.matches(web, WORKLOAD[n]).agg(F.lit(n).alias("query"), F.count("*").alias("n")) for n in ("q1", "q2")])


@register("cartesian_patterns", f"with web as ({web_sql()}) select a.doc as d0, b.doc as d1, a.s as a, b.s as b from (select * from web where p = 2 and o = 50) a, (select * from web where p = 1 and o = 33) b")
def cartesian_patterns(spark, sf_dir):
    return construct.solutions(reach.matches(web_of(spark, sf_dir).triples, PAIR), PAIR).select("a", "b", "d0", "d1")


# Reachability -------------------------------------------------------------------------------------------------------

for _name in SIX:

    @register(f"reach_{_name}", f"{ctes(_name)} select doc, depth::int as depth from reached")
    def _reach(spark, sf_dir, name=_name):
        return reached_by(spark, sf_dir, name).select("doc", "depth")


@register("reach_all_q2", f"{ctes('q2', 'all')} select doc, depth::int as depth from reached")
def reach_all_q2(spark, sf_dir):
    return reached_by(spark, sf_dir, "q2", "all").select("doc", "depth")


@register("reach_none_q2", f"{ctes('q2', 'none')} select doc, depth::int as depth from reached")
def reach_none_q2(spark, sf_dir):
    return reached_by(spark, sf_dir, "q2", "none").select("doc", "depth")


@register("reach_custom_q2", f"{reach.reach_ctes(WORKLOAD['q2'], web_sql(), ENTITY_SQL).replace(reach.condition_sql(WORKLOAD['q2']), 'p in (2, 4)')} select doc, depth::int as depth from reached")
def reach_custom_q2(spark, sf_dir):
    return reach.reach(web_of(spark, sf_dir), WORKLOAD["q2"], lambda q: F.col("p").isin(2, 4)).select("doc", "depth")


@register("depth_q4", f"{ctes('q4')} select depth::int as depth, count(*)::bigint as n from reached group by 1")
def depth_q4(spark, sf_dir):
    return reached_by(spark, sf_dir, "q4").groupBy("depth").agg(F.count("*").alias("n"))


@register("unreached_docs", f"{ctes('q2')} select uri as doc from ent where uri not in (select doc from reached)")
def unreached_docs(spark, sf_dir):
    return web_of(spark, sf_dir).resolve.where("doc is not null").select("doc").distinct().join(reached_by(spark, sf_dir, "q2").select("doc"), "doc", "left_anti")


@register("new_uris_round1", f"{ctes('q2')} select doc from reached where depth = 1")
def new_uris_round1(spark, sf_dir):
    return reached_by(spark, sf_dir, "q2").where("depth = 1").select("doc")


@register("failed_lookups", f"{ctes('q2')} select distinct uri from (select p::bigint * 16 as uri from web join reached using (doc) where {reach.condition_sql(WORKLOAD['q2'])} union all select 32 union all select 64)")
def failed_lookups(spark, sf_dir):
    return reach.failed_lookups(web_of(spark, sf_dir), WORKLOAD["q2"], reached_by(spark, sf_dir, "q2"))


@register("subweb_counts", f"{ctes('q2')} select count(distinct doc)::bigint as docs, count(*)::bigint as triples, count(distinct p)::bigint as predicates from web join reached using (doc)")
def subweb_counts(spark, sf_dir):
    held = web_of(spark, sf_dir).triples.join(reached_by(spark, sf_dir, "q2").select("doc"), "doc")
    return held.agg(F.countDistinct("doc").alias("docs"), F.count("*").alias("triples"), F.countDistinct("p").alias("predicates"))


@register("approx_subweb_docs")
def approx_subweb_docs(spark, sf_dir):
    return reached_by(spark, sf_dir, "q4").agg(F.approx_count_distinct("doc", 0.02).alias("docs"))


# Solutions ----------------------------------------------------------------------------------------------------------

for _name in SIX:
    _q = WORKLOAD[_name]
    _vars = ", ".join(_q.variables)

    @register(f"solutions_{_name}_bag", f"{solved(_name)} select {_vars}, {', '.join(f'd{i}' for i in range(_q.n))} from j")
    def _bag(spark, sf_dir, name=_name):
        q = WORKLOAD[name]
        return construct.solutions(matches_of(spark, sf_dir, name), q).select(*q.variables, *[f"d{i}" for i in range(q.n)])

    @register(f"solutions_{_name}_set", f"{solved(_name)} select distinct {_vars} from j")
    def _set(spark, sf_dir, name=_name):
        q = WORKLOAD[name]
        return construct.solutions(construct.distinct_matches(matches_of(spark, sf_dir, name)), q).select(*q.variables)

    @register(f"bag_count_{_name}", f"{solved(_name)} select (select count(*) from j)::bigint as n_bag, (select count(*) from (select distinct {_vars} from j))::bigint as n_set")
    def _count(spark, sf_dir, name=_name):
        got = construct.bag_count(matches_of(spark, sf_dir, name), WORKLOAD[name])
        return got.select(F.col("n_bag").cast("long").alias("n_bag"), "n_set")

    @register(
        f"rt_fifo_{_name}",
        f"{solved(_name)}, o as (select t, row_number() over (order by t) as k, count(*) over () as n from sol) select (select count(*) from reached)::bigint as n_docs, max(n)::bigint as n_solutions, min(t)::bigint as t_first, min(case when k = (n + 1) // 2 then t end)::bigint as t_half, max(t)::bigint as t_last from o having count(*) > 0",
    )
    def _times(spark, sf_dir, name=_name):
        n = reached_by(spark, sf_dir, name).agg(F.count("*").alias("n_docs"))
        return metrics.response_times(timed(spark, sf_dir, name), n).select("n_docs", "n_solutions", "t_first", "t_half", "t_last")


@register("solutions_q7_bag", f"""{ctes('q2')}, l as materialized ({literal_sql()}),
r7 as (select doc from reached)
select a.s as c, c.s as o, a.doc as d0, a.s as d1, c.doc as d2, c.s as d3 from web a join l b on a.s = b.s and b.p = {LITERALS['c_mktsegment']} and b.o_str = 'BUILDING' and a.s in (select doc from r7)
join web c on c.o = a.s and c.p = 4 and c.doc in (select doc from r7) join l d on d.s = c.s and d.p = {LITERALS['o_orderstatus']} and d.o_str = 'F' and c.s in (select doc from r7)
where a.p = 2 and a.o = 50 and a.doc in (select doc from r7)""")
def solutions_q7_bag(spark, sf_dir):
    q = WORKLOAD["q7"]
    return construct.solutions(matches_of(spark, sf_dir, "q7"), q).select(*q.variables, *[f"d{i}" for i in range(q.n)])


@register("full_web_q4", f"with w as materialized (select s as doc, s, p, o from ({LINK_SQL.strip()})) select p, l, s, n from ({join_sql(WORKLOAD['q4'], source='w')})")
def full_web_q4(spark, sf_dir):
    return construct.full_web(web_of(spark, sf_dir).triples, WORKLOAD["q4"])


@register("delta_join_once_q4", f"{solved('q4')} select p, l, s, n, d0, d1, d2, d3 from j")
def delta_join_once_q4(spark, sf_dir):
    """Batches by depth of the lookup: every solution comes from exactly one of them."""
    q = WORKLOAD["q4"]
    found = matches_of(spark, sf_dir, "q4").join(reached_by(spark, sf_dir, "q4").select("doc", "depth"), "doc")
    parts = [construct.delta(found.where((F.col("depth") >= lo) & (F.col("depth") < hi)), found.where(F.col("depth") < lo), q) for lo, hi in ((0, 2), (2, 4), (4, 99))]
    return reduce(DataFrame.unionByName, parts).select(*q.variables, *[f"d{i}" for i in range(q.n)])


@register("sql_solutions_q1", f"{solved('q1')} select o, l, p from j")
def sql_solutions_q1(spark, sf_dir):
    """The same through SQL over temporary views."""
    web_of(spark, sf_dir).triples.join(reached_by(spark, sf_dir, "q1").select("doc"), "doc").createOrReplaceTempView("web_triples")
    return spark.sql("select a.s as o, b.s as l, c.o as p from web_triples a join web_triples b on b.o = a.s join web_triples c on c.s = b.s where a.p = 4 and a.o = 115 and b.p = 5 and c.p = 6")


@register("solution_as_json")
def solution_as_json(spark, sf_dir):
    q = WORKLOAD["q2"]
    found = construct.solutions(matches_of(spark, sf_dir, "q2"), q)
    mapping = F.map_from_arrays(F.array(*map(F.lit, q.variables)), F.array(*[F.col(v).cast("string") for v in q.variables]))
    return found.select(F.to_json(mapping).alias("mapping"), F.to_json("prov").alias("documents"))


@register("provenance_size_q5", f"{solved('q5')} select n_docs::int as n_docs, count(*)::bigint as n from (select len(list_distinct([d0, d1, d2, d3, d4])) as n_docs from j) group by 1")
def provenance_size_q5(spark, sf_dir):
    return construct.solutions(matches_of(spark, sf_dir, "q5"), WORKLOAD["q5"]).groupBy(F.size("prov").alias("n_docs")).agg(F.count("*").alias("n"))


@register("index_size_asof", f"""{solved('q2')}, m as (select 0 as pattern_id, doc, s, p, o from seen where p = 2 and o = 50 union all select 1, doc, s, p, o from seen where p = 4),
n as (select m.*, rank, row_number() over (partition by doc order by s, p, o, pattern_id) as k from m join traced using (doc))
select pattern_id, doc, s, o, coalesce(sum((pattern_id = 0)::int) over w, 0)::bigint as size0, coalesce(sum((pattern_id = 1)::int) over w, 0)::bigint as size1 from n window w as (order by rank, k rows between unbounded preceding and 1 preceding)""")
def index_size_asof(spark, sf_dir):
    q = WORKLOAD["q2"]
    got = construct.asof_sizes(construct.stamped(matches_of(spark, sf_dir, "q2"), trace_of(spark, sf_dir, "q2")), q, bucket=64)
    return got.select("pattern_id", "doc", F.col("_s").alias("s"), F.col("_o").alias("o"), F.col("sizes")[0].alias("size0"), F.col("sizes")[1].alias("size1"))


def _hops(spark, sf_dir, name, routing):
    found = construct.asof_sizes(construct.stamped(matches_of(spark, sf_dir, name), trace_of(spark, sf_dir, name)), WORKLOAD[name])
    held = durable(found, "stamped")
    return construct.hops(held, held, WORKLOAD[name], routing)


for _policy in ("uniform", "lr", "lr_li", "lr_mi", "lr_mc", "lr_mc_li", "lr_mc_mi", "lr_mc_ls", "lr_mc_ms"):

    @register(f"route_{_policy}_q3", f"{solved('q3')} select c, n, r, s, d0, d1, d2, d3 from j")
    def _route(spark, sf_dir, policy=_policy):
        q = WORKLOAD["q3"]
        return _hops(spark, sf_dir, "q3", Routing(policy, seed=7))[0].select(*q.variables, *[f"d{i}" for i in range(q.n)])


@register("route_static_q1", f"{solved('q1')} select 'x' || ord as plan, o, l, p from j, (select unnest(range(6)) as ord)")
def route_static_q1(spark, sf_dir):
    """All six left-deep plans give the same solutions."""
    from .operators.routing import all_static

    parts = [_hops(spark, sf_dir, "q1", r)[0].select(F.lit(f"x{i}").alias("plan"), "o", "l", "p") for i, r in enumerate(all_static(WORKLOAD["q1"]))]
    return reduce(DataFrame.unionByName, parts)


@register("routed_stats_q2", f"{solved('q2')} select 1 as hop, (select count(*) from seen where p = 4 or (p = 2 and o = 50))::bigint as n_routed")
def routed_stats_q2(spark, sf_dir):
    return construct.routed_stats(_hops(spark, sf_dir, "q2", Routing("lr_mi"))[1])


@register("covered_histogram", f"{solved('q3')} select 1 as covered_patterns, (select count(*) from (select 1 from seen where p in (1, 2, 3) union all select 1 from seen where s = 182 and p = 4))::bigint as n")
def covered_histogram(spark, sf_dir):
    _, routed = _hops(spark, sf_dir, "q3", Routing("lr_mi"))
    return routed[0].groupBy(F.bit_count("covered").alias("covered_patterns")).agg(F.count("*").alias("n"))


# Orders and times ---------------------------------------------------------------------------------------------------


@register("fifo_rank", f"{ctes('q4')} select doc, rank::bigint as rank from traced")
def fifo_rank(spark, sf_dir):
    return trace_of(spark, sf_dir, "q4").select("doc", "rank")


@register("solution_curve", f"{solved('q4')} select t::bigint as t_avail, sum(count(*)) over (order by t)::bigint as upto from sol group by t")
def solution_curve(spark, sf_dir):
    return metrics.solution_curve(timed(spark, sf_dir, "q4")).select("t_avail", (F.col("before") + F.col("n")).alias("upto"))


@register("solution_gaps", f"{solved('q4')} select t::bigint as t_avail, (t - lag(t) over (order by t))::bigint as gap from (select distinct t from sol)")
def solution_gaps(spark, sf_dir):
    return metrics.solution_curve(timed(spark, sf_dir, "q4")).select("t_avail", (F.col("t_avail") - F.col("previous")).alias("gap"))


@register("kth_solution", f"{solved('q4')}, o as (select t, row_number() over (order by t) as k from sol) select k::int as k, t::bigint as t_avail from o where k in (1, 10, 100)")
def kth_solution(spark, sf_dir):
    return metrics.kth_solution(timed(spark, sf_dir, "q4"), (1, 10, 100))


@register("solution_quartiles", f"{solved('q4')} select quartile, min(t)::bigint as t_from, max(t)::bigint as t_to, count(*)::bigint as n from (select t, ntile(4) over (order by t)::int as quartile from sol) group by 1")
def solution_quartiles(spark, sf_dir):
    return metrics.tiles(timed(spark, sf_dir, "q4")).withColumnRenamed("tile", "quartile")


@register("response_curve_q4", f"{solved('q4')}, o as (select t, row_number() over (order by t) as k, count(*) over () as n from sol), f as (select unnest([0.1, 0.25, 0.5, 0.75, 0.9])::double as fraction) select fraction, min(t)::bigint as t from o, f where k >= ceil(fraction * n) group by 1")
def response_curve_q4(spark, sf_dir):
    return metrics.response_curve(timed(spark, sf_dir, "q4"), [0.1, 0.25, 0.5, 0.75, 0.9])


# Contributions, degrees, scores -------------------------------------------------------------------------------------


@register("rcc_q4", f"{solved('q4')} select doc, rcc::bigint as rcc from rcc")
def rcc_q4(spark, sf_dir):
    return linkgraph.rcc(timed(spark, sf_dir, "q4"))


@register("rcc_all_vertices", f"{solved('q2')} select doc, coalesce(rcc, 0)::bigint as rcc from reached left join rcc using (doc)")
def rcc_all_vertices(spark, sf_dir):
    return metrics.relevance(reached_by(spark, sf_dir, "q2"), timed(spark, sf_dir, "q2")).select("doc", "rcc")


@register("relevant_docs_q4", f"{solved('q4')} select doc from rcc")
def relevant_docs_q4(spark, sf_dir):
    return metrics.relevance(reached_by(spark, sf_dir, "q4"), timed(spark, sf_dir, "q4")).where("rcc > 0").select("doc")


@register("indegree_scores", f"{solved('q4')}, {LINKED} select dst as uri, count(*)::bigint as indegree from lk group by 1")
def indegree_scores(spark, sf_dir):
    return linkgraph.degrees(reached_links(spark, sf_dir, "q4"))[0]


@register("outdegree", f"{solved('q4')}, {LINKED} select src as doc, count(*)::bigint as outdegree from lk group by 1")
def outdegree(spark, sf_dir):
    return linkgraph.degrees(reached_links(spark, sf_dir, "q4"))[1]


@register("top_priority_uris", f"{solved('q4')}, {LINKED} select uri, indegree::bigint as indegree from (select dst as uri, count(*) as indegree from lk group by 1) order by indegree desc, uri limit 20")
def top_priority_uris(spark, sf_dir):
    return linkgraph.degrees(reached_links(spark, sf_dir, "q4"))[0].orderBy(F.desc("indegree"), "uri").limit(20)


@register("two_step_in_neighbours", f"{solved('q2')}, {LINKED} select src, dst from lk union select a.src, b.dst from lk a join lk b on a.dst = b.src where a.src <> b.dst")
def two_step_in_neighbours(spark, sf_dir):
    return linkgraph.two_step(reached_links(spark, sf_dir, "q2"))


for _measure in ("rcc", "rel"):
    for _steps in (1, 2):
        _pairs = "lk" if _steps == 1 else "(select src, dst from lk union select a.src, b.dst from lk a join lk b on a.dst = b.src where a.src <> b.dst)"

        @register(f"{_measure}{_steps}_scores", f"{solved('q2')}, {LINKED} select p.dst as uri, {'sum(rcc)' if _measure == 'rcc' else 'count(*)'}::bigint as score from {_pairs} p join rcc on rcc.doc = p.src group by 1")
        def _scores(spark, sf_dir, measure=_measure, steps=_steps):
            counts = linkgraph.rcc(timed(spark, sf_dir, "q2"))
            return linkgraph.solution_scores(reached_links(spark, sf_dir, "q2"), counts, steps).select("uri", F.col(f"{measure}_score").alias("score"))


@register("rcc_outdegree", f"{solved('q4')}, {LINKED}, od as (select src as doc, count(*) as outdegree from lk group by 1) select doc, coalesce(rcc, 0)::bigint as rcc, coalesce(outdegree, 0)::bigint as outdegree from reached left join rcc using (doc) left join od using (doc)")
def rcc_outdegree(spark, sf_dir):
    rated = metrics.relevance(reached_by(spark, sf_dir, "q4"), timed(spark, sf_dir, "q4"))
    return rated.join(linkgraph.degrees(reached_links(spark, sf_dir, "q4"))[1], "doc", "left").select("doc", "rcc", F.coalesce("outdegree", F.lit(0)).alias("outdegree"))


@register("corr_indegree_relevance", f"{solved('q4')}, {LINKED}, ind as (select dst as doc, count(*) as indegree from lk group by 1) select round(corr(coalesce(indegree, 0), (rcc is not null)::int), 6) as corr_indegree from reached left join rcc using (doc) left join ind using (doc)")
def corr_indegree_relevance(spark, sf_dir):
    rated = metrics.relevance(reached_by(spark, sf_dir, "q4"), timed(spark, sf_dir, "q4"))
    return metrics.correlation(rated, linkgraph.degrees(reached_links(spark, sf_dir, "q4"))[0], "indegree")


@register("corr_pagerank_relevance")
def corr_pagerank_relevance(spark, sf_dir):
    rated = metrics.relevance(reached_by(spark, sf_dir, "q2"), timed(spark, sf_dir, "q2"))
    return metrics.correlation(rated, linkgraph.pagerank(durable(reached_links(spark, sf_dir, "q2"), "links"), rounds=8).withColumnRenamed("rank", "pagerank"), "pagerank")


def _pagerank_sql(rounds: int) -> str:
    steps = "".join(
        f", r{i + 1} as materialized (select v.uri, 0.15 / n.n + 0.85 * (coalesce(m.got, 0) + (1 - coalesce((select sum(got) from (select sum(rank / degree) as got from lk join r{i} on r{i}.uri = lk.src join od on od.src = lk.src)), 0)) / n.n) as rank "
        f"from vs v left join (select dst as uri, sum(rank / degree) as got from lk join r{i} on r{i}.uri = lk.src join od on od.src = lk.src group by 1) m using (uri), n)"
        for i in range(rounds)
    )
    return f"{solved('q2')}, {LINKED}, vs as materialized (select src as uri from lk union select dst from lk), n as (select count(*) as n from vs), od as materialized (select src, count(*) as degree from lk group by 1), r0 as (select uri, 1 / n.n as rank from vs, n){steps} select uri, round(rank, 9) as rank from r{rounds}"


@register("pagerank_q2", _pagerank_sql(5))
def pagerank_q2(spark, sf_dir):
    return linkgraph.pagerank(durable(reached_links(spark, sf_dir, "q2"), "links"), rounds=5, tolerance=0.0).select("uri", F.round("rank", 9).alias("rank"))


def _table1_sql(name: str) -> str:
    far = lambda rel: f"case when {rel} and depth > 0 then depth end"
    distances = ", ".join(f"round(avg({far(r)}), 6) as {k}_mean, round(stddev_samp({far(r)}), 6) as {k}_sd, min({far(r)})::int as {k}_min, max({far(r)})::int as {k}_max" for k, r in (("relevant", "rel"), ("irrelevant", "not rel")))
    return (
        f"{solved(name)}, {LINKED}, r as (select depth, rcc is not null as rel from reached left join rcc using (doc)) select count(*)::bigint as docs, (select count(*) from lk where dst in (select doc from reached))::bigint as edges, "
        f"sum(rel::int)::bigint as relevant_docs, round(sum(rel::int) * 100 / count(*), 1) as relevant_pct, (select count(*) from sol)::bigint as result_size, {distances} from r"
    )


for _name in ("q2", "q3", "q4", "q6"):

    @register(f"table1_{_name}", _table1_sql(_name))
    def _table1(spark, sf_dir, name=_name):
        """Statistics of the reachable part of a web: components and diameter are queries of their own."""
        got = metrics.subweb_stats(reached_by(spark, sf_dir, name), reached_links(spark, sf_dir, name), timed(spark, sf_dir, name), deep=False)
        rounded = [F.round(c, 6).alias(c) if c.endswith(("mean", "sd")) else F.col(c) for k in ("relevant", "irrelevant") for c in (f"{k}_mean", f"{k}_sd", f"{k}_min", f"{k}_max")]
        return got.select("docs", F.col("edges").cast("long").alias("edges"), "relevant_docs", "relevant_pct", F.col("result_size").cast("long").alias("result_size"), *rounded)


def _diameter_sql(name: str, bound: int) -> str:
    return f"{solved(name)}, {LINKED}, e as materialized (select src, dst from lk where dst in (select doc from reached)), w(a, b, k) as (select doc, doc, 0 from reached union select w.a, e.dst, w.k + 1 from w join e on e.src = w.b where w.k < {bound}) select max(k)::int as diameter from (select a, b, min(k) as k from w group by 1, 2)"


@register("sccs_q2", f"{solved('q2')}, {LINKED}, e as materialized (select src, dst from lk where dst in (select doc from reached)), c(a, b) as (select src, dst from e union select c.a, e.dst from c join e on e.src = c.b) select doc as v, least(doc, coalesce(min(x.b), doc)) as component from reached left join (select c.a, c.b from c join c d on d.a = c.b and d.b = c.a) x on x.a = reached.doc group by doc")
def sccs_q2(spark, sf_dir):
    docs = reached_by(spark, sf_dir, "q2").select(F.col("doc").alias("v"))
    inner = reached_links(spark, sf_dir, "q2").join(docs.toDF("dst"), "dst", "left_semi")
    got = linkgraph.strong_components(docs, inner)
    low = got.groupBy("component").agg(F.min("v").alias("low"))
    return got.join(low, "component").select("v", F.col("low").alias("component"))


for _name in ("q2", "q3"):

    @register(f"diameter_{_name}", _diameter_sql(_name, 8))
    def _diameter(spark, sf_dir, name=_name):
        docs = reached_by(spark, sf_dir, name).select(F.col("doc").alias("v"))
        return spark.createDataFrame([(linkgraph.diameter(docs, reached_links(spark, sf_dir, name)),)], "diameter int")


@register("diameter_sampled_q4")
def diameter_sampled_q4(spark, sf_dir):
    """A lower bound from 32 sources: the sampling operator for webs whose pairs are too many."""
    docs = reached_by(spark, sf_dir, "q4").select(F.col("doc").alias("v"))
    return spark.createDataFrame([(linkgraph.diameter(docs, reached_links(spark, sf_dir, "q4"), sample=32),)], "diameter int")


@register("irrelevant_beyond_q4", f"{solved('q4')}, r as (select depth, rcc is not null as rel from reached left join rcc using (doc)), b as (select max(case when rel then depth end) as far, quantile_disc(case when not rel then depth end, 0.5) as mid from r) select sum((not rel and depth > far)::int)::bigint as irrelevant_beyond, sum((rel and depth < mid)::int)::bigint as relevant_before from r, b")
def irrelevant_beyond_q4(spark, sf_dir):
    rated = metrics.relevance(reached_by(spark, sf_dir, "q4"), timed(spark, sf_dir, "q4"))
    return metrics.predictors(rated, reached_links(spark, sf_dir, "q4")).select("irrelevant_beyond", "relevant_before")


@register("predictors_q2", f"{solved('q2')}, {LINKED}, one as (select distinct dst from lk where src in (select doc from rcc)), two as (select dst from one union select b.dst from lk a join lk b on b.src = a.dst where a.src in (select doc from rcc) and a.src <> b.dst) select (select count(*) from rcc where doc not in (select dst from one))::bigint as lone_1step, (select count(*) from rcc where doc not in (select dst from two))::bigint as lone_2step")
def predictors_q2(spark, sf_dir):
    rated = metrics.relevance(reached_by(spark, sf_dir, "q2"), timed(spark, sf_dir, "q2"))
    return metrics.predictors(rated, reached_links(spark, sf_dir, "q2")).select("lone_1step", "lone_2step")


# Comparators --------------------------------------------------------------------------------------------------------


@register("source_index", f"with web as ({web_sql()}) select p, doc, count(*)::bigint as n from web group by 1, 2")
def source_index(spark, sf_dir):
    """What a pre-collected index of sources holds: how many triples of each predicate a document has."""
    return web_of(spark, sf_dir).triples.groupBy("p", "doc").agg(F.count("*").alias("n"))


@register("index_select_q2", f"with web as ({web_sql()}) select doc, count(*)::bigint as score from web where p in (2, 4) group by 1")
def index_select_q2(spark, sf_dir):
    """Documents that the index selects for a query, with the number of triples that speak for them."""
    wanted = [t.p for t in WORKLOAD["q2"].patterns]
    return source_index(spark, sf_dir).where(F.col("p").isin(wanted)).groupBy("doc").agg(F.sum("n").alias("score"))


@register("index_then_indegree_q2", f"{solved('q2')}, {LINKED}, ix as (select doc, count(*) as score from web where p in (2, 4) group by 1), ind as (select dst as doc, count(*) as indegree from lk group by 1) select r.doc, coalesce(ix.score, ind.indegree, 0)::bigint as prio from reached r left join ix using (doc) left join ind using (doc)")
def index_then_indegree_q2(spark, sf_dir):
    """The mixed way: indexed documents by the index, others by known links."""
    degree = linkgraph.degrees(reached_links(spark, sf_dir, "q2"))[0].withColumnRenamed("uri", "doc")
    return reached_by(spark, sf_dir, "q2").select("doc").join(index_select_q2(spark, sf_dir), "doc", "left").join(degree, "doc", "left").select("doc", F.coalesce("score", "indegree", F.lit(0)).alias("prio"))


# Experiments by simulation ------------------------------------------------------------------------------------------


def _cells(spark, sf_dir, name, approaches, routings=("lr_mi",), webs=(CORPUS_LIKE,), runs=1):
    given = _once(spark, ("cellinputs", sf_dir, name, webs), lambda: experiments.cell_inputs(spark, sf_dir, (name,), webs))
    return _once(spark, ("cells", sf_dir, name, approaches, routings, webs, runs), lambda: durable(experiments.grid(spark, sf_dir, (name,), webs, approaches, routings, runs, given), "cells"))


#: Rank of a queued URI, least first, under the orders that SQL can follow: from the rank of its parent, and what is known of it beforehand.
ORDERS = {"fifo": "0.0", "depth_first": "r.now.rank - 1", "breadth_first": "r.now.rank + 1", "oracle_rcc": "-x.rcc", "random": "-x.draw"}


def ordered(name: str, order: str) -> str:
    """CTEs that end in run (step, doc): lookups one at a time, with queue and known URIs as lists; and upto (rank, doc, solutions)."""
    q = WORKLOAD[name]
    ranks = "".join(f" join run k{i} on k{i}.doc = j.d{i}" for i in range(q.n))
    t = f"greatest({', '.join(f'k{i}.step' for i in range(q.n))})"
    seeds = ", ".join(f"({u}, {i})" for i, u in enumerate(q.seeds()))
    first = {"oracle_rcc": "-coalesce(rcc, 0)::double", "random": f"-({draw_sql(0, 'ent.uri')})"}.get(order, "0.0::double")
    return f"""{solved(name)},
said as (select doc, uri, min(row(s, p, o, place)) as k from (select doc, s, p, o, unnest([0, 2]) as place, unnest([s, o]) as uri from seen where {reach.condition_sql(q)}) where uri in (select uri from ent) group by 1, 2),
told as materialized (select said.doc, list({{'uri': uri, 'rcc': coalesce(rcc.rcc, 0)::double, 'draw': {draw_sql(0, 'uri')}}} order by k) as uris from said left join rcc on rcc.doc = said.uri group by 1),
start as (select {{'rank': {first}, 'arrival': i::bigint, 'uri': ent.uri}} as x from (values {seeds}) v(uri, i) join ent using (uri) left join rcc on rcc.doc = ent.uri),
walked(step, now, queue, known) as (
  select 0::bigint, null::struct(rank double, arrival bigint, uri bigint), list(x), list(x.uri) from start
  union all
  select r.step, r.now, list_concat(list_filter(r.queue, lambda y: y.uri <> r.now.uri), list_transform(r.fresh, lambda x, i: {{'rank': ({ORDERS[order]})::double, 'arrival': (1000000 + len(r.known) + i)::bigint, 'uri': x.uri}})), list_concat(r.known, list_transform(r.fresh, lambda x: x.uri))
  from (select p.step + 1 as step, p.now, p.queue, p.known, list_filter(coalesce(told.uris, []), lambda x: not list_contains(p.known, x.uri)) as fresh
    from (select step, list_sort(queue)[1] as now, queue, known from walked where len(queue) > 0) p left join told on told.doc = p.now.uri) r),
run as materialized (select step, now.uri as doc from walked where step > 0),
times as materialized (select {t} as t from j{ranks}),
upto as (select step as rank, doc, coalesce((select count(*) from times where t <= step), 0)::bigint as solutions from run)"""


def _simulated_sql(approach: str) -> str:
    if approach in ORDERS:
        times = "(select min(t) from times)::bigint as t_first, (select quantile_disc(t, 0.5) from times)::bigint as t_half, (select max(t) from times)::bigint as t_last"
        return f"{ordered('q2', approach)} select '{approach}' as approach, (select count(*) from run)::bigint as n_docs, (select count(*) from times)::bigint as n_solutions, {times}"
    return f"{solved('q2')} select '{approach}' as approach, (select count(*) from reached)::bigint as n_docs, (select count(*) from sol)::bigint as n_solutions"


for _approach in (*APPROACHES, *LITERAL_HYBRIDS):

    @register(f"simulate_{_approach}_q2", _simulated_sql(_approach))
    def _simulate(spark, sf_dir, approach=_approach):
        """Order never changes what is reached nor what is found; where SQL can follow the order, the times are compared, too."""
        got = _cells(spark, sf_dir, "q2", (approach,))
        return got.select("approach", "n_docs", "n_solutions", *(("t_first", "t_half", "t_last") if approach in ORDERS else ()))


for _approach in (*APPROACHES, *LITERAL_HYBRIDS):

    @register(f"trace_{_approach}_q2", f"{ordered('q2', _approach)} select '{_approach}' as approach, rank, doc, solutions from upto" if _approach in ORDERS else None)
    def _trace(spark, sf_dir, approach=_approach):
        """The exact order of lookups."""
        got = _once(spark, ("traces", sf_dir), lambda: durable(_traces(spark, sf_dir), "traces"))
        return got.where(F.col("approach") == approach).select("approach", "rank", "doc", "solutions")


# Traversal in rounds, all state in tables


def _rounds(spark, sf_dir, name, approach, batch):
    def make():
        web, q, a = web_of(spark, sf_dir), WORKLOAD[name], APPROACHES[approach]
        # First come, first served needs a round for each level only.
        got = rounds.traverse(web, q, a, batch) if approach == "fifo" else rounds.execute(web, q, a, batch, reached_by(spark, sf_dir, name))
        return durable(got.trace, "roundtrace"), durable(got.solutions, "roundsolutions")

    return _once(spark, ("rounds", sf_dir, name, approach, batch), make)


for _approach in ("fifo", "oracle_rcc", "indegree", "pagerank", "partial_decay", "rel1", "partial_rcc1"):
    _q = WORKLOAD["q2"]

    @register(f"rounds_{_approach}_q2", f"{solved('q2')} select {', '.join(_q.variables)}, {', '.join(f'd{i}' for i in range(_q.n))} from j")
    def _in_rounds(spark, sf_dir, approach=_approach):
        """Solutions of the distributed traversal, many lookups at a time: each round of pagerank ranks to its tolerance, so there are fewer."""
        q = WORKLOAD["q2"]
        return _rounds(spark, sf_dir, "q2", approach, 512 if approach == "pagerank" else 128)[1].select(*q.variables, *[f"d{i}" for i in range(q.n)])


@register("rounds_trace_fifo_q2", f"{ordered('q2', 'fifo')} select rank, doc from upto")
def rounds_trace_fifo_q2(spark, sf_dir):
    """First come, first served is the same order whatever the batch."""
    return _rounds(spark, sf_dir, "q2", "fifo", 128)[0].select("rank", "doc")


@register("rounds_docs_q2", f"{solved('q2')} select a as approach, doc from reached, (select unnest(['fifo', 'indegree', 'rel1']) as a)")
def rounds_docs_q2(spark, sf_dir):
    return reduce(DataFrame.unionByName, [_rounds(spark, sf_dir, "q2", a, 128)[0].select(F.lit(a).alias("approach"), "doc") for a in ("fifo", "indegree", "rel1")])


def _traces(spark, sf_dir):
    web = web_of(spark, sf_dir)
    reached = reached_by(spark, sf_dir, "q2").select(F.lit(CORPUS_LIKE.web_id).alias("web_id"), F.lit("q2").alias("query"), "doc")
    return experiments.traces(web.triples, reached, "q2", (*APPROACHES, *LITERAL_HYBRIDS))


@register("trace_docs_q2", f"{solved('q2')} select a as approach, doc from reached, (select unnest([" + ", ".join(f"'{a}'" for a in (*APPROACHES, *LITERAL_HYBRIDS)) + "]) as a)")
def trace_docs_q2(spark, sf_dir):
    """Every approach looks up the same documents."""
    return _once(spark, ("traces", sf_dir), lambda: durable(_traces(spark, sf_dir), "traces")).select("approach", "doc")


@register("retrieval_model_q4", f"{ctes('q4')}, n as (select count(*) as n from reached) select k::int as threads, n::bigint as n_docs, ((n + k - 1) // k)::bigint as lookup_rounds from n, (select unnest([1, 2, 5, 10, 20]) as k)")
def retrieval_model_q4(spark, sf_dir):
    """Rounds of lookups by the number of threads: times the latency of one, the time that retrieval takes."""
    n = reached_by(spark, sf_dir, "q4").agg(F.count("*").alias("n_docs"))
    return n.select(F.explode(F.array(*map(F.lit, (1, 2, 5, 10, 20)))).alias("threads"), "n_docs").withColumn("lookup_rounds", F.expr("(n_docs + threads - 1) div threads"))


@register("rt_pivot")
def rt_pivot(spark, sf_dir):
    """Approaches by measure on the corpus-like web."""
    got = _cells(spark, sf_dir, "q2", (*APPROACHES, *LITERAL_HYBRIDS))
    long = got.select("approach", F.explode(F.map_from_arrays(F.array(F.lit("first"), F.lit("half"), F.lit("last")), F.array("relRT1st", "relRT50", "relRTCmpl"))).alias("measure", "value"))
    return long.groupBy("approach").pivot("measure", ["first", "half", "last"]).agg(F.first("value"))


@register("grid_worse_better_q2")
def grid_worse_better_q2(spark, sf_dir):
    """Shares of the fourteen webs at least a tenth worse or better than first come, first served."""
    return metrics.compare_to_baseline(_cells(spark, sf_dir, "q2", tuple(APPROACHES), webs=WEBS).where("n_solutions > 0"))


@register("grid_worse_better_by_density_q2")
def grid_by_density(spark, sf_dir):
    dense = F.col("web_id").isin([w.web_id for w in WEBS if w.dense])
    return metrics.compare_to_baseline(_cells(spark, sf_dir, "q2", tuple(APPROACHES), webs=WEBS).where("n_solutions > 0").withColumn("dense", dense), by=("dense",))


@register("grid_solution_counts_q2", ALL_WEBS_SQL.replace("with d as", "with recursive d as", 1) + f""", ent as materialized ({ENTITY_SQL}),
web as materialized (select web_id, unnest(case side when 'both' then [s, o] when 'subject' then [s] else [o] end) as doc, s, p, o from placed where p in (2, 4)),
m as materialized (select distinct * from web where p = 4 or (p = 2 and o = 50)),
edge as materialized (select distinct web_id, src, dst from (select web_id, doc as src, s as dst from m union all select web_id, doc, o from m) where src <> dst),
walk(web_id, doc) as (select web_id, 50::bigint from w union select e.web_id, e.dst from walk k join edge e on e.web_id = k.web_id and e.src = k.doc),
s as (select m.* from m join walk k using (web_id, doc)),
sol as (select a.web_id from s a join s b on a.web_id = b.web_id and b.o = a.s and b.p = 4 where a.p = 2)
select w.web_id, (select count(*) from walk k where k.web_id = w.web_id)::bigint as n_docs, (select count(*) from sol where sol.web_id = w.web_id)::bigint as n_solutions from w""")
def grid_solution_counts_q2(spark, sf_dir):
    return _cells(spark, sf_dir, "q2", ("partial_rel1",), webs=WEBS).select("web_id", "n_docs", "n_solutions")


@register("random_spread_q2")
def random_spread_q2(spark, sf_dir):
    """First and last solution over five random runs."""
    return metrics.aggregate_runs(_cells(spark, sf_dir, "q2", ("fifo", "random"), runs=5).where("n_solutions > 0"), ("web_id", "query", "approach"))


@register("geo_mean_rt", f"{solved('q2')} select count(*)::bigint as n, round(exp(avg(ln(t))), 6) as geo_mean from sol")
def geo_mean_rt(spark, sf_dir):
    return timed(spark, sf_dir, "q2").agg(F.count("*").alias("n"), F.round(F.exp(F.avg(F.log("t_avail"))), 6).alias("geo_mean"))


@register("routing_policies_q1")
def routing_policies_q1(spark, sf_dir):
    """All policies and all left-deep plans: what they route differs, response times don't."""
    return _cells(spark, sf_dir, "q1", ("fifo",), experiments.routing_names("q1")).select("routing", "routed", "n_solutions", "t_first", "t_last")


INTERMEDIATE = ("partial", "partial_decay", "partial_rcc1", "partial_rcc2", "partial_rel1", "partial_rel2")

for _name in ("q2",):

    @register(f"routing_by_approach_{_name}")
    def _routing_by_approach(spark, sf_dir, name=_name):
        """Approaches that look at partial solutions, under each policy; a query of two patterns leaves no choice."""
        got = _cells(spark, sf_dir, name, INTERMEDIATE, experiments.routing_names(name, static=False))
        return got.select("approach", "routing", "routed", "n_solutions", "t_first", "t_half", "t_last", "relRT1st", "relRT50", "relRTCmpl")


# Other webs ---------------------------------------------------------------------------------------------------------


@register("page_hosts", "select regexp_extract(split_part(url, '://', 2), '^([^/?#]*)', 1) as host, count(*)::bigint as n from pages group by 1")
def page_hosts(spark, sf_dir):
    return pages_web.page_parts(table(spark, sf_dir, "pages")).groupBy("host").agg(F.count("*").alias("n"))


@register("page_links", "select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages")
def page_links(spark, sf_dir):
    return pages_web.page_links(table(spark, sf_dir, "pages"))


@register("page_link_indegree", "select href, count(*)::bigint as indegree from (select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages) group by 1")
def page_link_indegree(spark, sf_dir):
    return pages_web.page_links(table(spark, sf_dir, "pages")).groupBy("href").agg(F.count("*").alias("indegree"))


@register("page_id_collision", "select count(distinct url)::bigint as urls, count(distinct url)::bigint as ids from pages")
def page_id_collision(spark, sf_dir):
    return table(spark, sf_dir, "pages").agg(F.countDistinct("url").alias("urls"), F.countDistinct(F.xxhash64("url")).alias("ids"))


@register("page_web_failed", "with t as (select distinct host, href from (select regexp_extract(split_part(url, '://', 2), '^([^/?#]*)', 1) as host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages)), g as (select distinct regexp_extract(split_part(url, '://', 2), '^([^/?#]*)', 1) as host, regexp_extract(split_part(url, '://', 2), '^[^/?#]*([^?#]*)', 1) as path from pages) select count(*)::bigint as failed from t where (host, href) not in (select host, path from g)")
def page_web_failed(spark, sf_dir):
    return pages_web.page_web(table(spark, sf_dir, "pages"))[1].where("doc is null").agg(F.count("*").alias("failed"))


@register("conversation_chain", "select distinct a.conv_id, a.turn from conversations a join conversations b on a.conv_id = b.conv_id and b.turn = a.turn + 1")
def conversation_chain(spark, sf_dir):
    triples, _ = pages_web.conversation_web(spark, sf_dir)
    node = F.expr("(doc - 10) div 16")
    return triples.select(F.expr("((doc - 10) div 16) div 4096").alias("conv_id"), F.pmod(node, F.lit(4096)).alias("turn"))


@register("parse_ntriples")
def parse_ntriples(spark, sf_dir):
    rows = table(spark, sf_dir, "nation").select(F.format_string('<http://n/%d> <http://name> "%s" .', "n_nationkey", "n_name").alias("value"))
    return pages_web.parse_ntriples(rows)


# Events and literals ------------------------------------------------------------------------------------------------



_EV = "count(*)::bigint as n, sum(round(value * 100)::bigint)::bigint as total"


@register("events_tumbling", f"select time_bucket(interval 1 hour, ts) as w_start, time_bucket(interval 1 hour, ts) + interval 1 hour as w_end, event_type, {_EV} from events group by all")
def events_tumbling(spark, sf_dir):
    return windows.tumbling(table(spark, sf_dir, "events"))


@register("events_sliding", f"select w as w_start, w + interval 1 hour as w_end, event_type, {_EV} from (select *, unnest([time_bucket(interval 15 minutes, ts) - interval 45 minutes, time_bucket(interval 15 minutes, ts) - interval 30 minutes, time_bucket(interval 15 minutes, ts) - interval 15 minutes, time_bucket(interval 15 minutes, ts)]) as w from events) group by all")
def events_sliding(spark, sf_dir):
    return windows.sliding(table(spark, sf_dir, "events"))


@register("events_session", f"select min(ts) as w_start, max(ts) + interval 30 minutes as w_end, user_id, {_EV} from (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as g from (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as fresh from events)) group by user_id, g")
def events_session(spark, sf_dir):
    return windows.sessions(table(spark, sf_dir, "events"))


@register("events_hourly", "select date_trunc('hour', ts) as hour, count(*)::bigint as n from events group by 1")
def events_hourly(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.count("*").alias("n"))


@register("events_rolling", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row)::bigint as recent from events")
def events_rolling(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return table(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("recent"))


@register("events_interval_join", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 10 minutes")
def events_interval_join(spark, sf_dir):
    """Pairs within ten minutes: both sides meet in buckets of that length, so the join has an equality to shuffle on."""
    ev = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 600_000_000).alias("bucket"))
    left = ev.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ts_a"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
    right = ev.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("ts_b"), "bucket")
    return left.join(right, ["user_id", "bucket"]).where((F.col("ts_b") > F.col("ts_a")) & (F.col("ts_b") <= F.col("ts_a") + F.expr("interval 10 minutes"))).select("a", "b")


@register("event_props_k", "select event_id, (props->>'$.k')::bigint as k from events")
def event_props_k(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@register("orders_by_month_literal", f"select date_trunc('month', o_ts)::timestamp as month, count(*)::bigint as n from ({literal_sql()}) where p = {LITERALS['o_orderdate']} group by 1")
def orders_by_month_literal(spark, sf_dir):
    lit = basegraph.literal_triples(spark, sf_dir).where(F.col("p") == LITERALS["o_orderdate"])
    return lit.groupBy(F.date_trunc("month", "o_ts").cast("timestamp_ntz").alias("month")).agg(F.count("*").alias("n"))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every solution of the second query on the corpus-like web, with the time at which it exists under first come, first served."""
    return timed(spark, sf_dir, "q2").orderBy("t_avail", "c", "o")
