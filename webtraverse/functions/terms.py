"""Term ids and reproducible draws, as columns.

A URI is ``key * 16 + type code``; predicates have code 0 and no document. Literals and blank nodes have negative ids, made by
hashing, so that every variable of a solution is one bigint column.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Type codes and predicate numbers of the base graph.
TYPES = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "orders": 6, "lineitem": 7, "brand": 8}
LINKS = {"in_region": 1, "c_nation": 2, "s_nation": 3, "o_cust": 4, "l_order": 5, "l_part": 6, "l_supp": 7, "p_brand": 8}
LITERALS = {
    "r_name": 20, "n_name": 21, "c_name": 22, "c_acctbal": 23, "c_mktsegment": 24, "s_name": 25, "s_acctbal": 26, "p_name": 27, "p_type": 28, "p_size": 29, "p_retailprice": 30,
    "o_orderstatus": 31, "o_totalprice": 32, "o_orderdate": 33, "o_orderpriority": 34, "l_quantity": 35, "l_extendedprice": 36, "l_discount": 37, "l_tax": 38, "l_returnflag": 39, "l_linestatus": 40, "l_shipdate": 41, "l_linenumber": 42,
}
PREDICATES = LINKS | LITERALS
URI, LITERAL, BLANK = 1, 2, 3
MODULUS = 2147483647


def uri(key: Column, kind: str) -> Column:
    return key.cast("long") * 16 + TYPES[kind]


def uri_of(key: int, kind: str) -> int:
    return key * 16 + TYPES[kind]


def predicate_uri(p) -> Column | int:
    return p * 16


def hashed_id(*parts: Column) -> Column:
    """A negative id for a literal or a blank node."""
    return -(F.xxhash64(*parts).bitwiseAND(F.lit(0x3FFFFFFFFFFFFFFF))) - 1


def uniform(s: Column, p: Column, o: Column, seed: int, factor: int) -> Column:
    """A draw from [0, 1) that depends on the triple and the seed alone; reduced first, so that nothing overflows."""
    m = F.lit(MODULUS)
    h = ((s % m) * 1000003 + p.cast("long") * 7919 + (o % m) * 31337 + seed * 101) % m
    return ((h * factor) % m) / m


def place_draws(s: Column, p: Column, o: Column, seed: int) -> tuple[Column, Column]:
    return uniform(s, p, o, seed, 48271), uniform(s, p, o, seed, 69621)


def draw(seed: int, uri: int) -> float:
    """A draw from [0, 1) that depends on the URI and the seed alone; the same in Python, Spark and SQL."""
    h = ((uri % MODULUS) * 48271 + (seed + 1) * 69621) % MODULUS
    return ((h * h + 7919 * h + 1) % MODULUS) / MODULUS


def seeded(seed: int, uri: Column) -> Column:
    """``draw`` as a column; it survives repartitioning and retries."""
    m = F.lit(MODULUS)
    h = ((uri % m) * 48271 + (seed + 1) * 69621) % m
    return ((h * h + h * 7919 + 1) % m) / m


def draw_sql(seed: int, uri: str) -> str:
    h = f"((({uri} % {MODULUS}) * 48271 + {(seed + 1) * 69621}) % {MODULUS})"
    return f"(({h} * {h} + 7919 * {h} + 1) % {MODULUS}) / {MODULUS}"
