"""The base graph: entities, links between them and literal attributes, projected from the relational tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.terms import LINKS, LITERALS, LITERAL, URI, hashed_id, uri

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def line_key():
    return F.col("l_orderkey") * 8 + F.col("l_linenumber")


def brand_key():
    return F.substring_index("p_brand", "#", -1).cast("long")


def _subject(kind: str):
    keys = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey"}
    return uri(line_key() if kind == "lineitem" else F.col(keys[kind]), kind)


def entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(uri, type, key), one row for each entity."""
    key = {"region": F.col("r_regionkey"), "nation": F.col("n_nationkey"), "customer": F.col("c_custkey"), "supplier": F.col("s_suppkey"), "part": F.col("p_partkey"), "orders": F.col("o_orderkey"), "lineitem": line_key()}
    parts = [table(spark, sf_dir, k).select(uri(c, k).alias("uri"), F.lit(k).alias("type"), c.cast("long").alias("key")) for k, c in key.items()]
    parts.append(table(spark, sf_dir, "part").select(uri(brand_key(), "brand").alias("uri"), F.lit("brand").alias("type"), brand_key().alias("key")).distinct())
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.dropDuplicates(["uri"])


#: predicate: (table, target type, target key)
_TARGETS = {
    "in_region": ("nation", "region", "n_regionkey"),
    "c_nation": ("customer", "nation", "c_nationkey"),
    "s_nation": ("supplier", "nation", "s_nationkey"),
    "o_cust": ("orders", "customer", "o_custkey"),
    "l_order": ("lineitem", "orders", "l_orderkey"),
    "l_part": ("lineitem", "part", "l_partkey"),
    "l_supp": ("lineitem", "supplier", "l_suppkey"),
    "p_brand": ("part", "brand", None),
}


def link_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(s, p, o), distinct: keys of line items are not unique, and a graph is a set. Each table is scanned once."""
    out = None
    for source in TABLES:
        own = {p: t for p, t in _TARGETS.items() if t[0] == source}
        if not own:
            continue
        links = [F.struct(F.lit(LINKS[p]).alias("p"), uri(brand_key() if key is None else F.col(key), kind).alias("o")) for p, (_, kind, key) in own.items()]
        rows = table(spark, sf_dir, source).select(_subject(source).alias("s"), F.explode(F.array(*links)).alias("x")).select("s", "x.p", "x.o")
        out = rows if out is None else out.unionByName(rows)
    return out.distinct()


def literal_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(s, p, o_str, o_dbl, o_ts), distinct; exactly one object column is set."""
    out = None
    for source in TABLES:
        frame = table(spark, sf_dir, source)
        kinds = dict(frame.dtypes)
        objects = []
        for p, number in LITERALS.items():
            if p not in kinds:
                continue
            kind, null = kinds[p], F.lit(None)
            objects.append(
                F.struct(
                    F.lit(number).alias("p"),
                    (F.col(p) if kind == "string" else null.cast("string")).alias("o_str"),
                    (F.col(p).cast("double") if kind in ("double", "int", "bigint") else null.cast("double")).alias("o_dbl"),
                    (F.col(p).cast("timestamp_ntz") if kind.startswith("timestamp") else null.cast("timestamp_ntz")).alias("o_ts"),
                )
            )
        rows = frame.select(_subject(source).alias("s"), F.explode(F.array(*objects)).alias("x")).select("s", "x.*")
        out = rows if out is None else out.unionByName(rows)
    return out.distinct()


def triples(spark: SparkSession, sf_dir: str, literals: bool = True) -> DataFrame:
    """All triples as (s, p, o_kind, o, o_str, o_dbl, o_ts)."""
    links = link_triples(spark, sf_dir).select("s", "p", F.lit(URI).cast("byte").alias("o_kind"), "o", F.lit(None).cast("string").alias("o_str"), F.lit(None).cast("double").alias("o_dbl"), F.lit(None).cast("timestamp_ntz").alias("o_ts"))
    if not literals:
        return links
    lit = literal_triples(spark, sf_dir)
    return links.unionByName(lit.select("s", "p", F.lit(LITERAL).cast("byte").alias("o_kind"), hashed_id("o_str", "o_dbl", "o_ts").alias("o"), "o_str", "o_dbl", "o_ts"))


# SQL twins for DuckDB -----------------------------------------------------------------------------------------------

LINK_SQL = """
select distinct s, p, o from (
  select n_nationkey::bigint * 16 + 2 as s, 1 as p, n_regionkey::bigint * 16 + 1 as o from nation
  union all select c_custkey * 16 + 3, 2, c_nationkey::bigint * 16 + 2 from customer
  union all select s_suppkey * 16 + 4, 3, s_nationkey::bigint * 16 + 2 from supplier
  union all select o_orderkey * 16 + 6, 4, o_custkey * 16 + 3 from orders
  union all select (l_orderkey * 8 + l_linenumber) * 16 + 7, 5, l_orderkey * 16 + 6 from lineitem
  union all select (l_orderkey * 8 + l_linenumber) * 16 + 7, 6, l_partkey * 16 + 5 from lineitem
  union all select (l_orderkey * 8 + l_linenumber) * 16 + 7, 7, l_suppkey * 16 + 4 from lineitem
  union all select p_partkey * 16 + 5, 8, split_part(p_brand, '#', 2)::bigint * 16 + 8 from part
)"""

ENTITY_SQL = """
select distinct uri, type, key from (
  select r_regionkey::bigint * 16 + 1 as uri, 'region' as type, r_regionkey::bigint as key from region
  union all select n_nationkey::bigint * 16 + 2, 'nation', n_nationkey::bigint from nation
  union all select c_custkey * 16 + 3, 'customer', c_custkey from customer
  union all select s_suppkey * 16 + 4, 'supplier', s_suppkey from supplier
  union all select p_partkey * 16 + 5, 'part', p_partkey from part
  union all select o_orderkey * 16 + 6, 'orders', o_orderkey from orders
  union all select (l_orderkey * 8 + l_linenumber) * 16 + 7, 'lineitem', l_orderkey * 8 + l_linenumber from lineitem
  union all select split_part(p_brand, '#', 2)::bigint * 16 + 8, 'brand', split_part(p_brand, '#', 2)::bigint from part
)"""


def literal_sql() -> str:
    own = {
        "region": ("r_regionkey::bigint * 16 + 1", {"r_name": "s"}),
        "nation": ("n_nationkey::bigint * 16 + 2", {"n_name": "s"}),
        "customer": ("c_custkey * 16 + 3", {"c_name": "s", "c_acctbal": "d", "c_mktsegment": "s"}),
        "supplier": ("s_suppkey * 16 + 4", {"s_name": "s", "s_acctbal": "d"}),
        "part": ("p_partkey * 16 + 5", {"p_name": "s", "p_type": "s", "p_size": "d", "p_retailprice": "d"}),
        "orders": ("o_orderkey * 16 + 6", {"o_orderstatus": "s", "o_totalprice": "d", "o_orderdate": "t", "o_orderpriority": "s"}),
        "lineitem": ("(l_orderkey * 8 + l_linenumber) * 16 + 7", {"l_quantity": "d", "l_extendedprice": "d", "l_discount": "d", "l_tax": "d", "l_returnflag": "s", "l_linestatus": "s", "l_shipdate": "t", "l_linenumber": "d"}),
    }
    parts = []
    for name, (subject, columns) in own.items():
        for column, kind in columns.items():
            cells = [f"{column}::varchar" if kind == "s" else "null::varchar", f"{column}::double" if kind == "d" else "null::double", f"{column}::timestamp" if kind == "t" else "null::timestamp"]
            parts.append(f"select {subject} as s, {LITERALS[column]} as p, {cells[0]} as o_str, {cells[1]} as o_dbl, {cells[2]} as o_ts from {name}")
    return "select distinct * from (" + " union all ".join(parts) + ")"
