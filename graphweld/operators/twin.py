"""Two heterogeneous graphs with known gold, derived from one world.

The first graph has readable ids and relation names. The second has opaque
ids and names, other literal forms (a way of writing strings, jittered
numbers, some dates moved by a day), a relation split by order status, two
relations merged into one, one turned around, and one that the first lacks. Facts and
whole entities are dropped on either side by md5 of keys, so Spark and DuckDB
build the same graphs.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweld.operators import facts as fx
from graphweld.plans.fact_rules import FULL, KINDS, PART, TYPES, FactRule, rules_sql
from graphweld.plans.lineage import cut


@dataclass(frozen=True)
class Profile:
    rules: tuple[FactRule, ...]
    fact_cut: str = "1a"
    dangling_cut: str = "00"
    strings: str = "lower(replace({}, '#', ' '))"


VOWELS = "translate(lower({}), 'aeiou', 'eioua')"
CONSONANTS = "translate(lower({}), 'rtlnsd', 'tlnsdr')"
BOTH = "translate(lower({}), 'aeiourtlnsd', 'eiouatlnsdr')"
_SMALL = tuple(q for q in FULL if q.table in ("part", "supplier", "nation", "region"))
PROFILES = {
    "tiny": Profile(PART),
    "sparse15": Profile(FULL, "66", "1a"),
    "dense15": Profile(FULL, "1a", "1a"),
    "cross_x": Profile(FULL, "33", "00", VOWELS),
    "cross_y": Profile(FULL, "33", "00", CONSONANTS),
    "cross_z": Profile(FULL, "33", "00", BOTH),
    "onto_m": Profile(FULL + TYPES, "33", "1a"),
    "onto_s": Profile(_SMALL + tuple(q for q in TYPES if q.table in ("part", "supplier", "nation", "region")), "33", "33"),
    "large": Profile(FULL, "33", "1a"),
}
#: Names of the second graph.
NAMES = {
    "label": "P1", "brand": "P2", "size": "P3", "kind": "P4", "price": "P5", "custName": "P6", "balance": "P7", "totalPrice": "P8", "orderDate": "P9", "inRegion": "P10", "type": "P11",
    "segment": "P12", "stockedBy": "P13", "nationName": "P14", "regionName": "P15", "suppName": "P16", "custNation": "located", "suppNation": "located", "item": "orderedIn", "priority": "priority",
}
STATUS = {"O": "buyerOpen", "F": "buyerDone", "P": "buyerPending"}
ONLY_A, ONLY_B = ("soldBy",), ("priority",)


def hashed(*parts: str) -> str:
    return f"substr(md5(concat_ws('|', {', '.join(parts)})), 1, 2)"


def _case(column: str, values: dict[str, str], otherwise: str) -> str:
    return f"CASE {' '.join(f"WHEN {column} = '{k}' THEN '{v}'" for k, v in values.items())} ELSE {otherwise} END"


def _opaque(kind: str, key: str) -> str:
    number = f"CASE {' '.join(f"WHEN {kind} = '{k}' THEN {n}" for k, n in KINDS.items())} END"
    return f"concat('Q', cast(cast({number} as bigint) * 1000000000 + (cast({key} as bigint) * 7919 + 13) % 1000003 as varchar(32)))"


def _readable(kind: str, key: str) -> str:
    return f"concat({kind}, '/', {key})"


def columns(profile: Profile, side: str) -> dict[str, str]:
    """SQL of one side's facts over base facts (hk, hid, r, tk, tid, x, part); both engines read it."""
    entity = "tk NOT IN ('string', 'number', 'date')"
    jitter = f"{hashed("'num'", 'hk', 'cast(hid as varchar(32))', 'r')} < '1a'"
    moved = f"{hashed("'day'", 'hk', 'cast(hid as varchar(32))', 'r')} < '1a'"
    if side == "A":
        return {
            "h": _readable("hk", "cast(hid as varchar(32))"),
            "r": "r",
            "t": f"CASE WHEN {entity} THEN {_readable('tk', 'tid')} WHEN tk = 'string' THEN concat('\"', tid) WHEN tk = 'number' THEN concat('#', tid) ELSE concat('@', tid) END",
            "kind": "tk",
            "x": "x",
        }
    day = "cast(cast(tid as date) + interval 1 day as date)"
    return {
        "h": _opaque("hk", "hid"),
        "r": _renamed(),
        "t": f"CASE WHEN tk = 'class' THEN concat('Thing', cast({_case('tid', {k: str(n) for k, n in KINDS.items()}, "'0'")} as varchar(32))) WHEN {entity} THEN {_opaque('tk', f'CASE WHEN {entity} AND tk <> {chr(39)}class{chr(39)} THEN tid ELSE {chr(39)}0{chr(39)} END')} "
        f"WHEN tk = 'string' THEN concat('\"', {profile.strings.format('tid')}) WHEN tk = 'number' THEN concat('#', tid, CASE WHEN {jitter} THEN '*' ELSE '' END) "
        f"WHEN {moved} THEN concat('@', cast(CASE WHEN tk = 'date' THEN {day.replace('tid', f'CASE WHEN tk = {chr(39)}date{chr(39)} THEN tid ELSE {chr(39)}2000-01-01{chr(39)} END')} END as varchar(32))) ELSE concat('@', tid) END",
        "kind": "tk",
        "x": f"CASE WHEN {jitter} THEN x * (1 + 1e-6) ELSE x * (1 + 1e-12) END",
    }


def conditions(profile: Profile, side: str) -> str:
    missing = ONLY_B if side == "A" else ONLY_A
    out = [f"r NOT IN ({', '.join(f"'{m}'" for m in missing)})", f"{hashed(f"'{side}'", 'hk', 'cast(hid as varchar(32))', 'r', 'tid')} >= '{profile.fact_cut}'"]
    if profile.dangling_cut != "00":
        gone = lambda kind, key: f"{hashed(f"'d{side}'", f'concat({kind}, {chr(39)}/{chr(39)}, {key})')} >= '{profile.dangling_cut}'"
        out.append(f"(hk NOT IN ('part', 'customer', 'order') OR {gone('hk', 'cast(hid as varchar(32))')})")
        out.append(f"(tk NOT IN ('part', 'customer', 'order') OR {gone('tk', 'tid')})")
    return " AND ".join(out)


def side_facts(base: DataFrame, profile: Profile, side: str) -> DataFrame:
    """facts (h, r, t, kind, x) of one graph."""
    c = {k: v.replace("as varchar(32)", "as string") for k, v in columns(profile, side).items()}
    rows = base.filter(conditions(profile, side).replace("as varchar(32)", "as string")).selectExpr(*(f"{v} AS {k}" for k, v in c.items()))
    turned = F.col("r") == "orderedIn"
    return rows.select(F.when(turned, F.col("t")).otherwise(F.col("h")).alias("h"), "r", F.when(turned, F.col("h")).otherwise(F.col("t")).alias("t"), F.when(turned, F.lit("order")).otherwise(F.col("kind")).alias("kind"), "x")


@dataclass
class Twin:
    a: DataFrame
    b: DataFrame
    gold: DataFrame
    gold_relations: DataFrame


def twin(spark: SparkSession, sf_dir: str, name: str) -> Twin:
    profile = PROFILES[name]
    base = cut(fx.base(spark, sf_dir, profile.rules))
    return Twin(side_facts(base, profile, "A"), side_facts(base, profile, "B"), gold_entities(base, profile), gold_relations(base))


def gold_entities(base: DataFrame, profile: Profile) -> DataFrame:
    """(e, e2, kind): entities of the first graph whose name in the second one stands there too.

    Names of the second graph repeat when keys of a kind pass 1000003, so entities may share one.
    """
    numbers = _case("i", {k: str(n) for k, n in KINDS.items()}, "'0'")

    def named(side: str) -> DataFrame:
        rows = base.filter(conditions(profile, side).replace("as varchar(32)", "as string"))
        keys = rows.select(F.col("hk").alias("k"), F.col("hid").cast("string").alias("i")).unionByName(rows.filter("tk NOT IN ('string', 'number', 'date')").select(F.col("tk").alias("k"), F.col("tid").alias("i"))).distinct()
        return keys.selectExpr(
            "concat(k, '/', i) AS e",
            f"CASE WHEN k = 'class' THEN concat('Thing', {numbers}) ELSE {_opaque('k', "CASE WHEN k = 'class' THEN '0' ELSE i END").replace('as varchar(32)', 'as string')} END AS e2",
            "CASE WHEN k = 'class' THEN 'class' ELSE 'instance' END AS kind",
        )

    return named("A").join(named("B").select("e2"), "e2", "left_semi").select("e", "e2", "kind")


def _renamed() -> str:
    """SQL of a base fact's relation in the second graph."""
    return f"CASE WHEN r = 'buyer' THEN {_case('part', STATUS, "'buyerOpen'")} ELSE {_case('r', NAMES, 'r')} END"


def relation_gold() -> str:
    """SQL over base facts: (r, op, r2) of the forward relations, by the names that the facts of each have in the second graph."""
    return f"""SELECT r, CASE WHEN count(*) OVER (PARTITION BY r) > 1 THEN 'super' WHEN count(*) OVER (PARTITION BY r2) > 1 THEN 'sub' ELSE 'equivalent' END AS op, CASE WHEN r2 = 'orderedIn' THEN 'orderedIn~' ELSE r2 END AS r2
        FROM (SELECT DISTINCT r, {_renamed()} AS r2 FROM base WHERE r NOT IN ({', '.join(f"'{r}'" for r in (*ONLY_A, *ONLY_B))}))"""


def gold_relations(base: DataFrame) -> DataFrame:
    return base.sparkSession.sql(relation_gold().replace("FROM base", "FROM {base}"), base=base)


def sql(name: str) -> str:
    """CTEs base, fa, fb (h, r, t, kind, x) and gold for DuckDB."""
    p = PROFILES[name]

    def side(s: str) -> str:
        c = columns(p, s)
        return f"SELECT CASE WHEN r = 'orderedIn' THEN t ELSE h END AS h, r, CASE WHEN r = 'orderedIn' THEN h ELSE t END AS t, CASE WHEN r = 'orderedIn' THEN 'order' ELSE kind END AS kind, x FROM (SELECT {', '.join(f'{v} AS {k}' for k, v in c.items())} FROM base WHERE {conditions(p, s)})"

    return f"base AS MATERIALIZED ({rules_sql(p.rules)}),\nfa AS MATERIALIZED ({side('A')}),\nfb AS MATERIALIZED ({side('B')})"
