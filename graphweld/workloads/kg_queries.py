"""Queries of the alignment methods with their SQL: facts, functionality, fuzzy systems, literals, rules, engine, baselines, measures."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweld.functions import aggregators as agg
from graphweld.operators import baselines, facts, fis, literals, metrics, rules
from graphweld.operators import functionality as fun
from graphweld.operators import twin as tw
from graphweld.plans.engine import align, explain
from graphweld.plans.fact_rules import FULL, PART
from graphweld.plans.lineage import cut, table
from graphweld.workloads import kg_sql as q

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a function under its name, with SQL if there is any."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE[f.__name__] = sql
        return f

    return add


_KEPT: dict = {}


def kept(f):
    """Remembers a function's checkpointed frames within an application, as many queries look at the same run."""

    @wraps(f)
    def run(spark, d, *args, **changes):
        key = (f.__name__, spark.sparkContext.applicationId, d, args, tuple(sorted(changes.items())))
        if key not in _KEPT:
            _KEPT[key] = f(spark, d, *args, **changes)
        return _KEPT[key]

    return run


def six(*columns: str):
    return [F.round(c, 6).alias(c) for c in columns]


PARTS, WHOLE = q.facts_sql(PART), q.facts_sql(FULL)
TINY = q.closed_sql("tiny")


def part_closed(spark, d):
    return facts.with_inverse(facts.build(spark, d, PART))


# ---------------------------------------------------------------- graph and twins


@query(f"WITH {PARTS} SELECT h, r, t, kind, round(x, 6) AS x FROM facts")
def kg_facts_part(spark, d):
    return facts.build(spark, d, PART).select("h", "r", "t", "kind", *six("x"))


@query(f"WITH {WHOLE} SELECT r, kind, count(*) AS n, count(DISTINCT h) AS heads, count(DISTINCT t) AS tails FROM facts GROUP BY r, kind")
def kg_facts_full(spark, d):
    """Heads and tails are grouped before they are counted, so no row is expanded for a distinct count."""
    f = cut(facts.build(spark, d, FULL).select("r", "kind", "h", "t"))
    heads = f.groupBy("r", "kind", "h").agg(F.count(F.lit(1)).alias("k")).groupBy("r", "kind").agg(F.sum("k").alias("n"), F.count(F.lit(1)).alias("heads"))
    tails = f.groupBy("r", "kind", "t").agg(F.count(F.lit(1)).alias("k")).groupBy("r", "kind").agg(F.count(F.lit(1)).alias("tails"))
    return heads.join(tails, ["r", "kind"]).select("r", "kind", "n", "heads", "tails")


@query(f"WITH {PARTS} SELECT * FROM closed")
def kg_inverse_closure(spark, d):
    return part_closed(spark, d)


@query(f"WITH {WHOLE}, n AS (SELECT t AS id, CASE WHEN kind IN ('string', 'number', 'date', 'class') THEN kind ELSE 'instance' END AS kind FROM facts UNION SELECT h, 'instance' FROM facts) SELECT kind, count(*) AS n FROM n GROUP BY kind")
def kg_nodes_by_kind(spark, d):
    return facts.nodes(facts.build(spark, d, FULL)).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


def _twin_facts(name):
    def run(spark, d):
        w = tw.twin(spark, d, name)
        return w.a.select(F.lit("A").alias("side"), "h", "r", "t").unionByName(w.b.select(F.lit("B").alias("side"), "h", "r", "t"))

    run.__name__ = f"twin_facts_{name}"
    return query(f"WITH {tw.sql(name)} SELECT 'A' AS side, h, r, t FROM fa UNION ALL SELECT 'B', h, r, t FROM fb")(run)


for _name in ("tiny", "sparse15", "dense15", "cross_y", "onto_s"):
    _twin_facts(_name)

_GOLD = tw.sql("dense15") + ", ids AS (SELECT DISTINCT 'part/' || p_partkey AS e, 'Q' || (5000000000 + (cast(p_partkey as bigint) * 7919 + 13) % 1000003) AS e2 FROM part UNION SELECT 'customer/' || c_custkey, 'Q' || (3000000000 + (cast(c_custkey as bigint) * 7919 + 13) % 1000003) FROM customer UNION SELECT 'order/' || o_orderkey, 'Q' || (6000000000 + (cast(o_orderkey as bigint) * 7919 + 13) % 1000003) FROM orders UNION SELECT 'supplier/' || s_suppkey, 'Q' || (4000000000 + (cast(s_suppkey as bigint) * 7919 + 13) % 1000003) FROM supplier UNION SELECT 'nation/' || n_nationkey, 'Q' || (2000000000 + (cast(n_nationkey as bigint) * 7919 + 13) % 1000003) FROM nation UNION SELECT 'region/' || r_regionkey, 'Q' || (1000000000 + (cast(r_regionkey as bigint) * 7919 + 13) % 1000003) FROM region), ina AS (SELECT h AS e FROM fa UNION SELECT t FROM fa), inb AS (SELECT h AS e2 FROM fb UNION SELECT t FROM fb)"


@query(f"WITH {_GOLD} SELECT e, e2, 'instance' AS kind FROM ids SEMI JOIN ina USING (e) SEMI JOIN inb USING (e2)")
def twin_gold_entities(spark, d):
    return tw.twin(spark, d, "dense15").gold


@query(f"WITH {tw.sql('onto_m')} {tw.relation_gold()}")
def twin_gold_relations(spark, d):
    return tw.twin(spark, d, "onto_m").gold_relations


@query(f"WITH {_GOLD} SELECT e FROM ids SEMI JOIN ina USING (e) ANTI JOIN inb USING (e2)")
def twin_dangling(spark, d):
    w = tw.twin(spark, d, "dense15")
    here = facts.nodes(w.a).filter("kind = 'instance'").select(F.col("id").alias("e"))
    return here.join(w.gold, "e", "left_anti")


# ---------------------------------------------------------------- functionality


@query(f"WITH {WHOLE} SELECT r, round(count(DISTINCT h) * 1.0 / count(*), 6) AS f FROM closed GROUP BY r")
def fun_global(spark, d):
    return fun.of_relations(facts.with_inverse(facts.build(spark, d, FULL))).select("r", *six("f"))


@query(f"WITH {PARTS} SELECT r, h, round(1.0 / count(*), 6) AS f FROM closed GROUP BY r, h")
def fun_local(spark, d):
    return fun.of_heads(part_closed(spark, d)).select("r", "h", *six("f"))


@query(f"WITH {WHOLE} SELECT r, round(count(DISTINCT t) * 1.0 / count(*), 6) AS f FROM facts GROUP BY r")
def fun_inverse(spark, d):
    f = fun.of_relations(facts.with_inverse(facts.build(spark, d, FULL))).filter("r LIKE '%~'")
    return f.select(facts.inverse_name(F.col("r")).alias("r"), *six("f"))


@query(f"WITH {PARTS}, inv AS (SELECT * FROM closed WHERE r LIKE '%~') SELECT x.r AS r1, y.r AS r2, count(*) AS n, count(DISTINCT x.t) AS tails, sum(length(x.h) + 3 * length(y.h) + 7 * length(x.t))::BIGINT AS mark FROM inv x JOIN inv y ON x.t = y.t AND (x.r, x.h) < (y.r, y.h) GROUP BY ALL")
def list_enum_2(spark, d):
    """All lists of two facts, told by their number, their tails and a sum over them."""
    mark = F.sum(F.length("h1") + 3 * F.length("h2") + 7 * F.length("t")).cast("long")
    return fun.pairs(part_closed(spark, d).filter("r LIKE '%~'")).groupBy("r1", "r2").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("t").alias("tails"), mark.alias("mark"))


@query(f"WITH {PARTS}, inv AS (SELECT * FROM closed WHERE r LIKE '%~' AND r IN ('brand~', 'price~', 'size~')) SELECT x.r || ',' || y.r || ',' || z.r AS rels, count(*) AS n, count(DISTINCT (x.h, y.h, z.h)) AS head_lists FROM inv x JOIN inv y ON x.t = y.t AND (x.r, x.h) < (y.r, y.h) JOIN inv z ON z.t = y.t AND (y.r, y.h) < (z.r, z.h) GROUP BY ALL")
def list_enum_3(spark, d):
    """Lists of three facts by two joins on the tail."""
    lists = fun.enumerate_lists(part_closed(spark, d).filter("r IN ('brand~', 'price~', 'size~')"), 3)
    rows = lists.select(F.array_join(F.transform("items", lambda x: x.r), ",").alias("rels"), F.transform("items", lambda x: x.h).alias("hs")).groupBy("rels", "hs").agg(F.count(F.lit(1)).alias("k"))
    return rows.groupBy("rels").agg(F.sum("k").alias("n"), F.count(F.lit(1)).alias("head_lists"))


@query(f"WITH {PARTS}, {q.pair_tables('closed', 'c')} SELECT r1, r2, round(f, 6) AS f FROM cp WHERE r1 LIKE '%~' AND r2 LIKE '%~'")
def fun_list_global_2(spark, d):
    return fun.of_pairs(part_closed(spark, d).filter("r LIKE '%~'")).select("r1", "r2", *six("f"))


@query(f"WITH {PARTS}, inv AS (SELECT * FROM closed WHERE r LIKE '%~'), {q.pair_tables('inv', 'c')} SELECT r1, h1, r2, h2, round(f, 6) AS f FROM cph")
def fun_list_local_2(spark, d):
    return fun.of_head_pairs(part_closed(spark, d).filter("r LIKE '%~'")).select("r1", "h1", "r2", "h2", *six("f"))


@query(f"WITH {PARTS}, inv AS (SELECT * FROM closed WHERE r LIKE '%~'), {q.pair_tables('inv', 'c')} SELECT r1, r2, count(*) AS n FROM cpairs GROUP BY r1, r2")
def list_pairs_binomial(spark, d):
    return fun.pair_counts(part_closed(spark, d).filter("r LIKE '%~'")).select("r1", "r2", F.col("n").cast("long").alias("n"))


@query(f"WITH {PARTS}, inv AS (SELECT * FROM closed WHERE r LIKE '%~'), {q.pair_tables('inv', 'c')} SELECT r1, r2, round(f, 6) AS f FROM cp")
def fun_list_mean_identity(spark, d):
    return fun.pair_mean_local(part_closed(spark, d).filter("r LIKE '%~'")).select("r1", "r2", *six("f"))


_ITEMS = tuple(x for x in FULL if x.relation in ("item", "stockedBy"))


@query(f"WITH {q.facts_sql(_ITEMS)}, fwd AS (SELECT h, r, t FROM facts WHERE r = 'item'), {q.pair_tables('fwd', 'c')} SELECT r1, r2, round(f, 6) AS f, (SELECT count(*) FROM cpairs) AS n FROM cp")
def fun_list_same_relation(spark, d):
    f = facts.build(spark, d, _ITEMS).filter("r = 'item'").select("h", "r", "t")
    return fun.of_pairs(f).join(fun.pair_counts(f), ["r1", "r2"]).select("r1", "r2", *six("f"), F.col("n").cast("long").alias("n"))


@query(f"WITH {PARTS}, inv AS (SELECT * FROM closed WHERE r LIKE '%~'), {q.pair_tables('inv', 'c')} SELECT r1 || ',' || r2 AS rels, round(f, 6) AS f FROM cp WHERE (r1, r2) IN (('brand~', 'label~'), ('price~', 'size~'), ('kind~', 'size~')) UNION ALL SELECT r, round(f, 6) FROM cr WHERE r = 'price~'")
def fun_list_on_demand(spark, d):
    wanted = spark.createDataFrame([(["brand~", "label~"],), (["price~", "size~"],), (["kind~", "size~"],), (["price~"],)], "rels array<string>")
    return fun.global_lists(part_closed(spark, d), wanted, 2).select(F.array_join("rels", ",").alias("rels"), *six("f"))


@query()
def fun_list_hll(spark, d):
    return fun.pair_approximate(part_closed(spark, d).filter("r LIKE '%~'"))


@query()
def fun_list_sampled(spark, d):
    return fun.pair_sampled(part_closed(spark, d).filter("r LIKE '%~'"), 500)


# ---------------------------------------------------------------- fuzzy systems

_FUZZY = "SELECT p_partkey AS k, least(1.0, greatest(0.0, (p_retailprice - 1000) / 600)) AS dear, least(1.0, greatest(0.0, (p_size - 10) / 30.0)) AS large FROM part"


def _fuzzy(spark, d):
    return fis.fuzzify(table(spark, d, "part"), {"dear": fis.ramp(F.col("p_retailprice"), 1000, 1600), "large": fis.ramp(F.col("p_size").cast("double"), 10, 40)}).select(F.col("p_partkey").alias("k"), "dear", "large")


@query(f"SELECT k, round(dear, 6) AS dear, round(large, 6) AS large FROM ({_FUZZY})")
def fuzzify_price(spark, d):
    return _fuzzy(spark, d).select("k", *six("dear", "large"))


@query(f"SELECT k, round(least(dear, large), 6) AS strength FROM ({_FUZZY})")
def fire_rules_min(spark, d):
    return _fuzzy(spark, d).select("k", F.round(agg.weakest(F.array("dear", "large")), 6).alias("strength"))


_GRID = [(0.0, 1.0, 0.0), (30.0, 0.5, 0.5), (60.0, 0.0, 1.0), (90.0, 0.0, 1.0)]
_GRID_SQL = "(VALUES " + ", ".join(f"({a}::DOUBLE, {b}::DOUBLE, {c}::DOUBLE)" for a, b, c in _GRID) + ") g(x, slow, fast)"
_COMBINED = f"SELECT k, x, greatest(least(fast, least(dear, large)), least(slow, 1 - greatest(dear, large))) AS mu FROM ({_FUZZY}), {_GRID_SQL}"


def _combined(spark, d):
    grid = spark.createDataFrame(_GRID, "x double, slow double, fast double")
    rows = _fuzzy(spark, d).join(F.broadcast(grid))
    fast = fis.cap(rows.withColumn("mu", F.col("fast")), F.least("dear", "large"))
    slow = fis.cap(rows.withColumn("mu", F.col("slow")), 1 - F.greatest("dear", "large"))
    return fis.combine(fast.unionByName(slow), "k")


@query(f"SELECT k, x, round(mu, 6) AS mu FROM ({_COMBINED})")
def mamdani_cap_combine(spark, d):
    return _combined(spark, d).select("k", "x", *six("mu"))


@query(f"SELECT k, min(x) AS x FROM (SELECT k, x, round(mu, 9) AS mu, max(round(mu, 9)) OVER (PARTITION BY k) AS m FROM ({_COMBINED})) WHERE mu = m GROUP BY k")
def first_of_maxima(spark, d):
    return fis.first_of_maxima(_combined(spark, d).withColumn("mu", F.round("mu", 9)), "k")


_SYSTEM = ([("r1", "fan", "min", 1.0), ("r2", "crowd", "identity", 1.0), ("r3", "shop", "hmean", 1.0), ("r4", "queue", "alpha_mean", 3.0), ("r5", "queue", "min", 1.0)], [("r1", 0, "heat"), ("r1", 1, "crowd"), ("r2", 0, "fan"), ("r3", 0, "fan"), ("r3", 1, "heat"), ("r4", 0, "shop"), ("r4", 1, "none"), ("r4", 2, "none"), ("r5", 0, "shop"), ("r5", 1, "crowd")], [("heat", 2 / 3, True), ("none", 0.0, True), ("crowd", 0.5, False), ("fan", 0.0, False), ("shop", 0.0, False), ("queue", 0.0, False)])


def _system(spark):
    r, p, v = _SYSTEM
    return spark.createDataFrame(r, "rule string, conclusion string, agg string, alpha double"), spark.createDataFrame(p, "rule string, pos int, var string"), spark.createDataFrame(v, "var string, floor double, fixed boolean")


@query("SELECT var, round(value, 6) AS value FROM (VALUES ('heat', 2.0 / 3), ('none', 0.0), ('crowd', 0.5), ('fan', 0.5), ('shop', 2 / (1.5 + 2)), ('queue', 2 / (1.5 + 2))) v(var, value)")
def fis_fixed_point_demo(spark, d):
    return fis.solve(*_system(spark), epsilon=1e-8).select("var", *six("value"))


def _part_systems(spark, d):
    """(rules, premises, vars) of the same system once for each part, whose size fixes the heat."""
    r, p, v = _SYSTEM
    own = lambda name: F.concat(F.lit(f"{name}/"), F.col("k").cast("string"))
    parts = _fuzzy(spark, d)

    def every(rows):
        return parts.select(F.inline(F.array(*rows)))

    rules_ = every([F.struct(own(a).alias("rule"), own(b).alias("conclusion"), F.lit(c).alias("agg"), F.lit(x).alias("alpha")) for a, b, c, x in r])
    premises = every([F.struct(own(a).alias("rule"), F.lit(n).alias("pos"), own(b).alias("var")) for a, n, b in p])
    return rules_, premises, every([F.struct(own(a).alias("var"), (F.col("large") if a == "heat" else F.lit(x)).alias("floor"), F.lit(fixed).alias("fixed")) for a, x, fixed in v])


@query(f"SELECT 'r1/' || k AS rule, 'fan/' || k AS conclusion, round(least(large, 0.5), 6) AS strength, 0.0::DOUBLE AS value FROM ({_FUZZY}) WHERE large > 1e-9")
def fis_violations(spark, d):
    """Rules that the floors of all parts' systems break: only r1 has premises above its conclusion."""
    r, p, v = _part_systems(spark, d)
    return fis.violations(r, p, v.withColumn("value", F.col("floor"))).select("rule", "conclusion", *six("strength"), F.col("value").cast("double").alias("value"))


@query(f"SELECT 'shop/' || k AS var, 1.0::DOUBLE AS value FROM ({_FUZZY}) UNION ALL SELECT 'queue/' || k, 1.0 FROM ({_FUZZY}) UNION ALL SELECT 'fan/' || k, 1.0 FROM ({_FUZZY}) WHERE large < 1 - 1e-9")
def fis_minimality(spark, d):
    """Every free variable at 1, without the rules of shop and queue: these two rest on nothing, fan only on a part that is not large enough."""
    r, p, v = _part_systems(spark, d)
    dropped = r.filter("NOT rule RLIKE '^r[345]/'")
    return fis.not_minimal(dropped, p, v.withColumn("value", F.when(F.col("fixed"), F.col("floor")).otherwise(1.0)))


_DEGREES = "SELECT r, h, 1.0 / count(*) AS v FROM closed GROUP BY r, h"


def _degree_rows(spark, d):
    return fun.of_heads(part_closed(spark, d))


for _agg, _sql in (("min", "min(v)"), ("hmean", "count(*) / sum(1 / v)"), ("alpha_mean", "least(1.0, 3 * avg(v))"), ("product", "exp(sum(ln(v)))"), ("lukasiewicz", "greatest(0.0, sum(v) - (count(*) - 1))"), ("mean", "avg(v)")):

    def _run(spark, d, name=_agg):
        rows = _degree_rows(spark, d)
        if name in ("product", "lukasiewicz"):
            rows = rows.filter("r IN ('label', 'price~')").withColumn("r", F.concat("r", F.substring("h", 1, 8)))
        return rows.groupBy("r").agg(F.round(agg.grouped(name, F.col("f")), 6).alias("v"))

    _run.__name__ = f"agg_{_agg}"
    _key = "r || substr(h, 1, 8)" if _agg in ("product", "lukasiewicz") else "r"
    _where = "WHERE r IN ('label', 'price~')" if _agg in ("product", "lukasiewicz") else ""
    query(f"WITH {PARTS} SELECT {_key} AS r, round({_sql}, 6) AS v FROM ({_DEGREES}) {_where} GROUP BY ALL".replace(f"SELECT {_key} AS r, round", f"SELECT {_key} AS r, round"))(_run)


# ---------------------------------------------------------------- literals


@kept
def _tiny(spark, d):
    return tw.twin(spark, d, "tiny")


def _strings(f):
    return f.filter("kind = 'string'").select(F.expr("substring(t, 2)").alias("s")).distinct()


@query(f"WITH {tw.sql('dense15')} SELECT DISTINCT substr(fa.t, 2) AS s, substr(fb.t, 2) AS s2, 1.0::DOUBLE AS sim FROM fa JOIN fb ON fa.t = fb.t AND fa.kind = 'string' AND fb.kind = 'string'")
def lit_identity(spark, d):
    w = tw.twin(spark, d, "dense15")
    return literals.identical(_strings(w.a), _strings(w.b))


@query(f"WITH {tw.sql('dense15')} SELECT DISTINCT fa.t FROM fa JOIN fb ON fa.t = fb.t AND fa.kind = 'date' AND fb.kind = 'date'")
def lit_dates(spark, d):
    w = tw.twin(spark, d, "dense15")
    return w.a.filter("kind = 'date'").select("t").distinct().join(w.b.filter("kind = 'date'").select("t").distinct(), "t")


@query(f"WITH {tw.sql('tiny')}, {q.NUMBERS} SELECT * FROM nums")
def lit_numbers_band(spark, d):
    w = _tiny(spark, d)
    return literals.numbers_close(w.a.filter("kind = 'number'").select(F.col("t").alias("n"), "x"), w.b.filter("kind = 'number'").select(F.col("t").alias("n2"), F.col("x").alias("x2")))


@query(f"WITH {tw.sql('tiny')}, {q.string_sims()} SELECT s, s2, round(sim, 6) AS sim FROM sims")
def lit_ngram_cosine(spark, d):
    w = _tiny(spark, d)
    return literals.strings_similar(_strings(w.a), _strings(w.b), 0.7, None).select("s", "s2", *six("sim"))


_PART_CROSS = "cross_x"
_SKELETON = "regexp_replace(lower(s), '[aeiou]', '', 'g')"


@query(f"WITH {tw.sql('cross_x')}, fap AS (SELECT * FROM fa WHERE r = 'label'), fbp AS (SELECT * FROM fb WHERE r = 'P1'), {q.string_sims(0.7, _SKELETON, 'fap', 'fbp')} SELECT s, s2, round(sim, 6) AS sim FROM sims")
def lit_skeleton_cosine(spark, d):
    w = tw.twin(spark, d, "cross_x")
    return literals.strings_similar(_strings(w.a.filter("r = 'label'")), _strings(w.b.filter("r = 'P1'")), 0.7, None, "skeleton").select("s", "s2", *six("sim"))


@query(f"WITH {tw.sql('tiny')}, {q.string_sims()}, {q.BEST} SELECT s, s2, round(sim, 6) AS sim FROM best")
def lit_top1(spark, d):
    w = _tiny(spark, d)
    return literals.strings_similar(_strings(w.a), _strings(w.b)).select("s", "s2", *six("sim"))


def _vectors(spark, d):
    e = table(spark, d, "embeddings")
    bumped = F.transform("embedding", lambda x, i: x.cast("double") + F.when(i == F.pmod(F.col("vec_id"), F.lit(64)), 0.1).otherwise(0.0))
    return e.select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v")), e.select(F.col("vec_id").alias("id2"), bumped.alias("v2"))


@query("""WITH v AS (SELECT vec_id, [x::DOUBLE FOR x IN embedding] AS v FROM embeddings), w AS (SELECT vec_id, [v[i]::DOUBLE + CASE WHEN i - 1 = vec_id % 64 THEN 0.1::DOUBLE ELSE 0 END FOR i IN generate_series(1, 64)] AS v FROM v),
s AS (SELECT v.vec_id AS id, w.vec_id AS id2, list_cosine_similarity(v.v, w.v) AS sim FROM v, w) SELECT id, id2, round(sim, 6) AS sim FROM s WHERE sim >= 0.7 QUALIFY row_number() OVER (PARTITION BY id ORDER BY sim DESC, id2) = 1""")
def lit_vectors_top1(spark, d):
    return literals.vector_top1(*_vectors(spark, d)).select("id", "id2", *six("sim"))


@query()
def lit_lsh(spark, d):
    return literals.vector_lsh(*_vectors(spark, d))


# ---------------------------------------------------------------- one round of rules

_ROUND0 = f"{TINY}, {q.literal_matches()}, {q.cp_sql('lm', None, '1')}, {q.candidates_sql('1')}"
_FUN = f"{q.pair_tables('a', 'a')}, {q.pair_tables('(SELECT r2 AS r, h2 AS h, t2 AS t FROM b)', 'b')}"


def _round0(spark, d):
    w = _tiny(spark, d)
    return facts.with_inverse(w.a), facts.with_inverse(w.b), cut(literals.matches(w.a, w.b))


@kept
def _counterparts(spark, d, search=True):
    a, b, m = _round0(spark, d)
    a, b = cut(a), cut(b)
    cp = cut(rules.counterparts(a, b, m))
    if search:
        cp = cut(cp.join(rules.candidates(cp).select("t", "t2"), ["t", "t2"], "left_semi"))
    return a, b, m, cp


@query(f"WITH {_ROUND0} SELECT r, r2, count(*) AS n, count(DISTINCT t) AS t_n, count(DISTINCT t2) AS t2_n FROM cp1 GROUP BY r, r2")
def counterparts_part(spark, d):
    cp = _counterparts(spark, d, False)[3]
    return cp.groupBy("r", "r2").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("t").alias("t_n"), F.count_distinct("t2").alias("t2_n"))


@query(f"WITH {_ROUND0} SELECT * FROM cand1")
def candidates_structural(spark, d):
    return rules.candidates(_counterparts(spark, d, False)[3])


@query(f"WITH {_ROUND0}, {_FUN}, {q.entity_sql('1')} SELECT t, t2, r, h, r2, h2, 1 AS pos FROM first1 UNION ALL SELECT t, t2, r, h, r2, h2, 2 FROM second1")
def rank_pairs(spark, d):
    items = rules.ranked_lists(_counterparts(spark, d)[3], 2).select("t", "t2", F.posexplode("items").alias("pos", "i"))
    return items.select("t", "t2", "i.r", "i.h", "i.r2", "i.h2", (F.col("pos") + 1).alias("pos"))


@query(f"WITH {_ROUND0}, {_FUN}, {q.entity_sql('1')} SELECT t, t2, n, round(score, 6) AS score FROM sc1")
def prefix_scores(spark, d):
    a, b, _, cp = _counterparts(spark, d)
    lists = rules.prefixes(rules.ranked_lists(cp, 2), 2)
    each = lists.withColumn("t2", F.concat_ws("|", "t2", F.col("n").cast("string")))  # one list a pair
    rows = rules.entity_scores(a, b, cp, lists=cut(each), longest=2)
    return rows.select("t", F.substring_index("t2", "|", 1).alias("t2"), F.substring_index("t2", "|", -1).cast("int").alias("n"), *six("score"))


def _entity_query(name, longest, minimum=False):
    def run(spark, d):
        a, b, _, cp = _counterparts(spark, d)
        return rules.entity_scores(a, b, cp, longest=longest, minimum=minimum).select("t", "t2", *six("score"))

    run.__name__ = name
    return query(f"WITH {_ROUND0}, {_FUN}, {q.entity_sql('1', longest, minimum)} SELECT t, t2, round(score, 6) AS score FROM es1")(run)


_entity_query("entity_round0", 2)
_entity_query("entity_round0_single", 1)
_entity_query("entity_round0_min", 2, True)


@query(f"""WITH {_ROUND0}, {_FUN}, c AS MATERIALIZED (SELECT * FROM cp1 SEMI JOIN cand1 USING (t, t2)),
l AS (SELECT c.t, c.t2, round(least(s_h, s_r, ar.f, arh.f, br.f, brh.f), 9) AS score FROM c JOIN ar ON ar.r = c.r JOIN arh ON arh.r = c.r AND arh.h = c.h JOIN br ON br.r = c.r2 JOIN brh ON brh.r = c.r2 AND brh.h = c.h2
UNION ALL SELECT f.t, f.t2, round(least(2 / (1 / f.s_h + 1 / g.s_h), 2 / (1 / f.s_r + 1 / g.s_r), p1.f, p2.f, q1.f, q2.f), 9) FROM c f JOIN c g ON f.t = g.t AND f.t2 = g.t2 AND (f.r, f.h) < (g.r, g.h) AND NOT (f.r2 = g.r2 AND f.h2 = g.h2)
  JOIN ap p1 ON p1.r1 = f.r AND p1.r2 = g.r JOIN aph p2 ON p2.r1 = f.r AND p2.h1 = f.h AND p2.r2 = g.r AND p2.h2 = g.h
  JOIN bp q1 ON q1.r1 = least(f.r2, g.r2) AND q1.r2 = greatest(f.r2, g.r2)
  JOIN bph q2 ON (q2.r1, q2.h1) = (CASE WHEN (f.r2, f.h2) < (g.r2, g.h2) THEN (f.r2, f.h2) ELSE (g.r2, g.h2) END) AND (q2.r2, q2.h2) = (CASE WHEN (f.r2, f.h2) < (g.r2, g.h2) THEN (g.r2, g.h2) ELSE (f.r2, f.h2) END))
SELECT t, t2, round(max(score), 6) AS score FROM l GROUP BY t, t2""")
def entity_subsets_2(spark, d):
    a, b, _, cp = _counterparts(spark, d)
    return rules.entity_scores(a, b, cp, longest=2, lists=cut(rules.subset_lists(cp))).select("t", "t2", *six("score"))


_AFTER0 = f"{_ROUND0}, {_FUN}, {q.entity_sql('1')}, {q.mutual_sql('es1', 'mm1')}, nodes1 AS MATERIALIZED (SELECT h, h2, s FROM lm UNION ALL SELECT t, t2, score FROM mm1 WHERE score > 0)"


@kept
def _after0(spark, d):
    a, b, m, cp = _counterparts(spark, d)
    best = rules.mutual_max(rules.entity_scores(a, b, cp, longest=2))
    return a, b, cut(m.unionByName(best.select(F.col("t").alias("h"), F.col("t2").alias("h2"), F.col("score").alias("s"))))


@query(f"WITH {_AFTER0}, {q.relation_sql('nodes1', '1')} SELECT r, r2, count(*) AS n, round(sum(m), 6) AS m FROM wit1 GROUP BY r, r2")
def witness_facts(spark, d):
    a, b, nodes = _after0(spark, d)
    return rules.witnesses(a.filter("NOT r LIKE '%~'"), b, nodes).groupBy("r", "r2").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("m"), 6).alias("m"))


@query(f"WITH {_AFTER0}, {q.relation_sql('nodes1', '1')} SELECT r, r2, round(cov, 6) AS coverage, round(sub, 6) AS degree FROM sub1")
def subrelation_round1(spark, d):
    a, b, nodes = _after0(spark, d)
    return rules.subrelations(a.filter("NOT r LIKE '%~'"), b, nodes).select("r", "r2", *six("coverage", "degree"))


@query(f"WITH {_AFTER0}, {q.relation_sql('nodes1', '1')} SELECT r, r2, round(sub, 6) AS sub, round(sup, 6) AS sup, round(s_r, 6) AS s_r FROM fwd1")
def relation_similarity(spark, d):
    a, b, nodes = _after0(spark, d)
    return rules.relation_pairs(a.filter("NOT r LIKE '%~'"), b, nodes).select("r", "r2", *six("sub", "sup", "s_r"))


@query(f"WITH {_AFTER0}, {q.relation_sql('nodes1', '1')} SELECT r, r2, CASE WHEN sub > 0 AND sup > 0 THEN 'equivalent' WHEN sub > 0 THEN 'sub' ELSE 'super' END AS op FROM fwd1 WHERE sub > 0 OR sup > 0")
def relation_verdicts(spark, d):
    a, b, nodes = _after0(spark, d)
    return rules.verdicts(rules.relation_pairs(a.filter("NOT r LIKE '%~'"), b, nodes)).select("r", "r2", "op")


@query(f"WITH {_AFTER0}, {q.relation_sql('nodes1', '1')} SELECT r, r2, alpha, round(least(1.0, alpha * cov), 6) AS degree FROM sub1, (VALUES (1.0::DOUBLE), (1.5), (2.0), (3.0), (5.0), (10.0), (100.0)) v(alpha)")
def subrelation_alpha_sweep(spark, d):
    a, b, nodes = _after0(spark, d)
    rows = rules.subrelations(a.filter("NOT r LIKE '%~'"), b, nodes).withColumn("alpha", F.explode(F.array(*map(F.lit, (1.0, 1.5, 2.0, 3.0, 5.0, 10.0, 100.0)))))
    return rows.select("r", "r2", "alpha", F.round(F.least(F.lit(1.0), F.col("alpha") * F.col("coverage")), 6).alias("degree"))


# ---------------------------------------------------------------- the loop

_SEEDS = "SELECT 'part/' || p_partkey AS t, 'Q' || (5000000000 + (cast(p_partkey as bigint) * 7919 + 13) % 1000003) AS t2 FROM part WHERE substr(md5('seed|' || p_partkey), 1, 2) < '33'"


def seeds(spark, d):
    key = F.col("p_partkey")
    rows = table(spark, d, "part").filter(F.substring(F.md5(F.concat(F.lit("seed|"), key.cast("string"))), 1, 2) < "33")
    return rows.select(F.concat(F.lit("part/"), key.cast("string")).alias("t"), F.concat(F.lit("Q"), (F.lit(5000000000) + (key * 7919 + 13) % 1000003).cast("string")).alias("t2"))


def _two(name, sql, **changes):
    def run(spark, d):
        w = _tiny(spark, d)
        found = align(w.a, w.b, rounds=2, theta_e=-1.0, longest=changes.get("longest", 2), minimum=changes.get("minimum", False), seeds=seeds(spark, d) if changes.get("seeded") else None)
        return found.entities.select("t", "t2", *six("score"))

    run.__name__ = name
    return query(f"WITH {sql} SELECT t, t2, round(score, 6) AS score FROM mm2")(run)


_two("align_two_rounds", q.two_rounds())
_two("align_two_rounds_min", q.two_rounds(minimum=True), minimum=True)
_two("align_two_rounds_len1", q.two_rounds(longest=1), longest=1)
_two("align_two_rounds_seeded", q.two_rounds(seeds=_SEEDS), seeded=True)
