"""The declared mapping from tables to facts, rendered as a DataFrame plan or as SQL.

A rule says which table it reads, the kind and key of the head, the relation,
the kind and key of the tail, and the tail's number if it is one. Fragments are
SQL that Spark and DuckDB read alike. Keys of numbers are cents, as the two
engines print doubles differently.
"""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class FactRule:
    table: str
    head_kind: str
    head: str
    relation: str
    tail_kind: str
    tail: str
    number: str | None = None
    #: Used only for the second graph of a twin, to split a relation.
    part: str = "''"


def money(column: str) -> tuple[str, str]:
    return f"cast(cast(round({column} * 100) as bigint) as varchar(32))", column


PART = (
    FactRule("part", "part", "p_partkey", "label", "string", "p_name"),
    FactRule("part", "part", "p_partkey", "brand", "string", "p_brand"),
    FactRule("part", "part", "p_partkey", "kind", "string", "p_type"),
    FactRule("part", "part", "p_partkey", "size", "number", *money("cast(p_size as double)")),
    FactRule("part", "part", "p_partkey", "price", "number", *money("p_retailprice")),
)
FULL = (
    *PART,
    FactRule("orders", "order", "o_orderkey", "buyer", "customer", "cast(o_custkey as varchar(32))", part="o_orderstatus"),
    FactRule("orders", "order", "o_orderkey", "orderDate", "date", "cast(cast(o_orderdate as date) as varchar(32))"),
    FactRule("orders", "order", "o_orderkey", "totalPrice", "number", *money("o_totalprice")),
    FactRule("customer", "customer", "c_custkey", "custNation", "nation", "cast(c_nationkey as varchar(32))"),
    FactRule("supplier", "supplier", "s_suppkey", "suppNation", "nation", "cast(s_nationkey as varchar(32))"),
    FactRule("customer", "customer", "c_custkey", "custName", "string", "c_name"),
    FactRule("customer", "customer", "c_custkey", "balance", "number", *money("c_acctbal")),
    FactRule("customer", "customer", "c_custkey", "segment", "string", "c_mktsegment"),
    FactRule("lineitem", "order", "l_orderkey", "item", "part", "cast(l_partkey as varchar(32))"),
    FactRule("lineitem", "order", "l_orderkey", "soldBy", "supplier", "cast(l_suppkey as varchar(32))"),
    FactRule("lineitem", "part", "l_partkey", "stockedBy", "supplier", "cast(l_suppkey as varchar(32))"),
    FactRule("nation", "nation", "n_nationkey", "inRegion", "region", "cast(n_regionkey as varchar(32))"),
    FactRule("nation", "nation", "n_nationkey", "nationName", "string", "n_name"),
    FactRule("region", "region", "r_regionkey", "regionName", "string", "r_name"),
    FactRule("supplier", "supplier", "s_suppkey", "suppName", "string", "s_name"),
    FactRule("orders", "order", "o_orderkey", "priority", "string", "o_orderpriority"),
)
TYPES = tuple(
    FactRule(table, kind, key, "type", "class", f"'{kind}'")
    for table, kind, key in (("part", "part", "p_partkey"), ("orders", "order", "o_orderkey"), ("customer", "customer", "c_custkey"), ("supplier", "supplier", "s_suppkey"), ("nation", "nation", "n_nationkey"), ("region", "region", "r_regionkey"))
)
LITERALS = ("string", "number", "date")
#: Numbers of the entity kinds in opaque ids.
KINDS = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6, "class": 7}


def rules_sql(rules: tuple[FactRule, ...]) -> str:
    """Distinct base facts (hk, hid, r, tk, tid, x, part) as SQL."""
    return "\nUNION ALL\n".join(
        f"SELECT DISTINCT '{q.head_kind}' AS hk, cast({q.head} as bigint) AS hid, '{q.relation}' AS r, '{q.tail_kind}' AS tk, {q.tail} AS tid, cast({q.number or 'NULL'} as double) AS x, {q.part} AS part "
        f"FROM {q.table} WHERE {q.head} IS NOT NULL AND {q.tail} IS NOT NULL"
        for q in rules
    )
