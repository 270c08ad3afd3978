"""Worked examples with exact answers, and invariants of the rules and of the whole loop."""

import math
import random

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from graphweld.functions import aggregators as agg
from graphweld.operators import baselines, facts, fis, literals, metrics, rules
from graphweld.operators import functionality as fun
from graphweld.operators import twin as tw
from graphweld.operators.overlap import most_shared
from graphweld.plans.fact_rules import PART
from graphweld.plans.lineage import cut
from graphweld.plans.engine import Params, align, explain, search

FACTS = "h string, r string, t string"
KIND = "h string, r string, t string, kind string, x double"


def triples(spark, text):
    return spark.createDataFrame([tuple(x.split()) for x in text.split(",")], FACTS)


def values(df, *keys):
    return {tuple(r[k] for k in keys): r.f for r in df.collect()}


def test_functionality_of_capitals(spark):
    f = triples(spark, "FR cap Paris,DE cap Berlin,ZA cap P,ZA cap B,ZA cap C")
    assert values(fun.of_relations(f), "r")["cap",] == 3 / 5
    assert values(fun.of_heads(f), "h") == {("FR",): 1, ("DE",): 1, ("ZA",): pytest.approx(1 / 3)}
    assert values(fun.of_relations(facts.with_inverse(f)), "r")["cap~",] == 1


def test_lists_of_two(spark):
    f = triples(spark, "1980 birth p1,1980 birth p2,1975 birth p3,Li family p1,Wu family p2,Li family p3")
    single = values(fun.of_relations(f), "r")
    assert single == {("birth",): pytest.approx(2 / 3), ("family",): pytest.approx(2 / 3)}
    assert values(fun.of_pairs(f), "r1", "r2") == {("birth", "family"): 1.0}
    wanted = spark.createDataFrame([(["birth", "family"],), (["birth"],)], "rels array<string>")
    assert {tuple(r.rels): r.f for r in fun.global_lists(f, wanted, 2).collect()} == {("birth", "family"): 1.0, ("birth",): pytest.approx(2 / 3)}
    assert fun.enumerate_lists(f, 2).count() == 3 and fun.enumerate_lists(f, 1).count() == 6
    assert fun.pair_counts(f).first().n == 3


def test_aggregators(spark):
    cases = {"hmean": [([1.0, 0.5], 2 / 3), ([1.0, 0.0], 0.0)], "alpha_mean": [([1.0, 0.0, 0.0], 1.0), ([0.1, 0.0], 0.15)], "lukasiewicz": [([0.7, 0.6], 0.3)], "product": [([0.5, 0.5], 0.25)], "min": [([0.4, 0.2], 0.2)], "max": [([0.4, 0.2], 0.4)], "mean": [([0.4, 0.2], 0.3)], "identity": [([0.4], 0.4)]}
    for name, rows in cases.items():
        df = spark.createDataFrame([(i, v) for i, (v, _) in enumerate(rows)], "i int, v array<double>")
        got = {r.i: r.a for r in df.select("i", agg.ARRAY[name](F.col("v")).alias("a")).collect()}
        grouped = {r.i: r.a for r in df.select("i", F.explode("v").alias("d")).groupBy("i").agg(agg.grouped(name, F.col("d")).alias("a")).collect()}
        for i, (v, want) in enumerate(rows):
            assert got[i] == pytest.approx(want) == agg.PLAIN[name](v)
            assert grouped[i] == pytest.approx(want)
    assert all(agg.admissible(f) for n, f in agg.PLAIN.items() if n != "identity")
    assert not agg.admissible(lambda v: 1 - v[0]) and not agg.admissible(lambda v: float(v[0] > 0.5))


def test_fan_example(spark):
    df = spark.createDataFrame([(20.0,)], "x double").select(fis.ramp(F.col("x"), 10, 25).alias("m"))
    assert df.first().m == pytest.approx(2 / 3)
    grid = spark.createDataFrame([(float(x), 1.0 if x > 60 else 0.0) for x in (0, 30, 60, 61, 90)], "x double, mu double")
    assert fis.first_of_maxima(fis.cap(grid, F.lit(0.5))).first().x == 61


def system(spark, rules_, floors):
    r = [(str(i), c, a, 3.0) for i, (a, _, c) in enumerate(rules_)]
    p = [(str(i), k, v) for i, (_, ps, _) in enumerate(rules_) for k, v in enumerate(ps)]
    return spark.createDataFrame(r, "rule string, conclusion string, agg string, alpha double"), spark.createDataFrame(p, "rule string, pos int, var string"), spark.createDataFrame([(k, float(v), False) for k, v in floors.items()], "var string, floor double, fixed boolean")


def test_slow_limit_halves_its_gap():
    rules_ = [("mean", ["hot", "crowd"], "fan"), ("identity", ["fan"], "crowd")]
    for n, want in ((1, 7 / 12), (2, 5 / 8), (3, 31 / 48)):
        assert fis.solve_plain(rules_, {"hot": 2 / 3, "crowd": 0.5, "fan": 0.0}, rounds=n)["fan"] == pytest.approx(want)


def test_solver_finds_the_least_fixed_point(spark):
    r = random.Random(3)
    names = [f"v{i}" for i in range(6)]
    rules_ = [(r.choice(["min", "hmean", "product", "mean"]), r.sample(names, 2), r.choice(names)) for _ in range(6)]
    floors = {n: round(r.random() * 0.6, 2) for n in names}
    a = fis.solve_plain(rules_, floors)
    b = fis.solve_plain(rules_[::-1], floors, sequential=False)
    assert a == pytest.approx(b, abs=1e-6)
    tables = system(spark, rules_, floors)
    found = fis.solve(*tables, epsilon=1e-4, rounds=25)
    got = {x.var: x.value for x in found.collect()}
    assert got == pytest.approx(a, abs=2e-2) and all(got[k] >= floors[k] for k in names)
    assert fis.violations(*tables[:2], found, 1e-2).count() == 0 and fis.not_minimal(*tables[:2], found, 1e-6).count() == 0


def test_numbers_within_relative_error(spark):
    a = spark.createDataFrame([(str(x), x) for x in (7245.31, 0.0, 5.0, -5.0)], "n string, x double")
    b = spark.createDataFrame([("near", 7245.31 * (1 + 1e-12)), ("far", 7245.31 * (1 + 1e-6)), ("zero", 0.0), ("tiny", 1e-12), ("minus", -5.0)], "n2 string, x2 double")
    assert {(r.n, r.n2) for r in literals.numbers_close(a, b).collect()} == {("7245.31", "near"), ("0.0", "zero"), ("-5.0", "minus")}


def test_assignment(spark):
    s = spark.createDataFrame([("a", "x", 0.9), ("a", "y", 0.8), ("b", "x", 0.7), ("b", "y", 0.8)], "t string, t2 string, score double")
    pairs = lambda df: {(r.t, r.t2) for r in df.collect()}
    assert pairs(rules.mutual_max(s)) == {("a", "x"), ("b", "y")}
    tie = spark.createDataFrame([("a", "x", 0.9), ("a", "y", 0.9)], "t string, t2 string, score double")
    assert pairs(rules.mutual_max(tie)) == {("a", "x"), ("a", "y")} and pairs(rules.one_to_one(tie)) == {("a", "x")}
    assert pairs(rules.greedy(s, 2)) == {("a", "x"), ("b", "y")}


def test_ranking_measures(spark):
    scored = spark.createDataFrame([("a", "a2", 0.9), ("b", "x", 0.9), ("b", "b2", 0.5)], "e string, e2 string, score double")
    gold = spark.createDataFrame([("a", "a2"), ("b", "b2"), ("c", "c2")], "e string, e2 string")
    r = metrics.ranking(scored, gold).first()
    assert (r.hit_at_1, r.hit_at_10, r.mrr) == pytest.approx((1 / 3, 2 / 3, 0.5))
    p = metrics.prf(scored.select("e", "e2"), gold).first()
    assert (p.right_n, p.predicted_n, p.gold_n) == (2, 3, 3) and p.f1 == pytest.approx(2 / 3)
    assert metrics.prf(scored.limit(0), gold).first().f1 == 0


def test_father_is_a_parent(spark):
    a, b = triples(spark, "a parent x,a parent y"), triples(spark, "a2 father x2")
    nodes = spark.createDataFrame([("a", "a2", 1.0), ("x", "x2", 1.0)], "h string, h2 string, s double")
    degree = lambda alpha: rules.relation_pairs(a, b, nodes, alpha).first()
    assert (degree(1.0).sub, degree(1.0).sup, degree(1.0).cov) == (0.5, 1.0, 0.5) and degree(3.0).sub == 1.0
    assert rules.subrelations(a, b, nodes, minimum=True).first().degree == 0.0


def test_functionality_bounds_the_score(spark):
    a, b = triples(spark, "a parent x,b parent y,b parent z"), triples(spark, "a2 parent x2,b2 parent y2,b2 parent z2")
    heads = spark.createDataFrame([("a", "a2", 1.0)], "h string, h2 string, s double")
    sure = spark.createDataFrame([("parent", "parent", 1.0)], "r string, r2 string, s_r double")
    cp = rules.counterparts(a, b, heads, sure)
    assert rules.entity_scores(a, b, cp, longest=1).first().score == pytest.approx(2 / 3, abs=1e-6)
    assert rules.entity_scores(a, b, cp, longest=1, terms=("local",)).first().score == 1.0


def test_a_longer_prefix_can_win(spark):
    a, b = triples(spark, "h1 r x,h2 s x"), triples(spark, "k1 r2 y,k2 s2 y")
    heads = spark.createDataFrame([("h1", "k1", 1.0), ("h2", "k2", 0.5)], "h string, h2 string, s double")
    sims = spark.createDataFrame([("r", "r2", 0.5), ("s", "s2", 1.0)], "r string, r2 string, s_r double")
    cp = rules.counterparts(a, b, heads, sims)
    assert rules.entity_scores(a, b, cp, longest=1).first().score == 0.5
    assert rules.entity_scores(a, b, cp, longest=2).first().score == pytest.approx(2 / 3, abs=1e-6)
    assert rules.entity_scores(a, b, cp, longest=2, minimum=True).first().score == 0.5


@pytest.fixture(scope="module")
def people(spark):
    a = spark.createDataFrame([("p1", "date", "@D", "date", None), ("p2", "date", "@D", "date", None), ("p1", "name", '"xxxx', "string", None), ("p2", "name", '"yyyy', "string", None)], KIND)
    b = spark.createDataFrame([("q1", "dob", "@D", "date", None), ("q2", "dob", "@D", "date", None), ("q1", "nm", '"xxxx', "string", None), ("q2", "nm", '"yyyy', "string", None)], KIND)
    return a, b


def test_trace_of_the_loop(people):
    found = align(*people, longest=2)
    assert [round(h["total"], 6) for h in found.history] == [0.2, 0.6, 1.8, 2.0, 2.0]
    assert {(r.t, r.t2, r.score) for r in found.entities.collect()} == {("p1", "q1", 1.0), ("p2", "q2", 1.0)}
    assert {(r.r, r.r2) for r in rules.verdicts(found.relations).filter("op = 'equivalent'").collect()} >= {("date", "dob"), ("name", "nm")}
    reason = explain(found.entities, "p1").first()
    assert reason.facts == 1 or reason.facts == 2


def test_without_benefit_of_the_doubt_nothing_grows(people):
    found = align(*people, alpha=1.0, rounds=2)
    assert found.scores.agg(F.max("score")).first()[0] == pytest.approx(0.1) and found.entities.count() == 0


def test_scores_only_grow_without_assignment(people):
    found = align(*people, assign_each_round=False, direction=None, longest=2, rounds=4)
    totals = [h["total"] for h in found.history]
    assert totals == sorted(totals)
    crossed = {(r.t, r.t2): r.score for r in found.scores.collect()}
    assert crossed["p1", "q2"] == 0.5 and crossed["p1", "q1"] == 1.0


def test_seeds_stay(spark, people):
    seeds = spark.createDataFrame([("p1", "q2")], "t string, t2 string")
    found = align(*people, seeds=seeds, longest=1, rounds=2)
    assert {(r.t, r.t2): r.score for r in found.scores.collect()}["p1", "q2"] == 1.0


def test_popular_heads_change_no_candidate(spark):
    r = random.Random(2)
    side = lambda mark, keep: [(f"{mark}{i}", k, v + w, "string", None) for i in range(60) for k, v, w in ((f"{mark}kind", '"', "abc"[i % 3] * 4), (f"{mark}town", '"', f"town{i % 7}"), (f"{mark}name", '"', f"name{i:03d}xyz")) if r.random() < keep]
    a, b = (spark.createDataFrame(side(m, 0.7), KIND) for m in "ab")
    ca, cb = facts.with_inverse(a).cache(), facts.with_inverse(b).cache()
    heads = literals.matches(a, b).cache()
    key = lambda df: {(x.t, x.t2) for x in df.select("t", "t2").collect()}
    every = key(search(ca, cb, heads, None, Params(hub=None)))
    assert every and all(key(search(ca, cb, heads, None, Params(hub=h))) == every for h in (1, 5, 12))


def test_partners_are_counted_in_blocks(spark):
    draw = random.Random(7)
    kinds = ["r", "s"]
    a = spark.createDataFrame([(f"h{draw.randrange(6)}", draw.choice(kinds), f"t{i % 40}") for i in range(160)], "h string, r string, t string").distinct()
    b = spark.createDataFrame([(f"k{draw.randrange(6)}", draw.choice(kinds) + "2", f"u{i % 50}") for i in range(200)], "h string, r string, t string").distinct()
    heads = spark.createDataFrame([(f"h{i}", f"k{(i + d) % 6}", s) for i in range(6) for d, s in ((0, 1.0), (1, 0.5), (2, 0.0))], "h string, h2 string, s double")
    sims = spark.createDataFrame([("r", "r2", 1.0), ("s", "s2", 0.5), ("s", "r2", 0.2), ("r", "s2", 0.0)], "r string, r2 string, s_r double")
    key = lambda df: sorted((r.t, r.t2) for r in df.collect())
    for relations in (None, sims):
        every = key(rules.candidates(rules.counterparts(a, b, heads, relations)))
        assert every and all(key(most_shared(a, b, heads, relations, *sizes)) == every for sizes in ((50_000, 300_000), (7, 30)))


def test_classes_are_found_through_instances(spark):
    rows = lambda m, names: [x for i, n in enumerate(names) for x in ((f"{m}{i}", f"{m}name", '"' + n, "string", None), (f"{m}{i}", f"{m}type", f"{m}class{i % 2}", "class", None))]
    names = ["aardvark", "buffalo", "crocodile", "dromedary", "elephant", "flamingo"]
    found = align(spark.createDataFrame(rows("a", names), KIND), spark.createDataFrame(rows("b", names), KIND), longest=2)
    assert found.settled
    got = {(x.t, x.t2): x.score for x in found.entities.collect()}
    assert got["aclass0", "bclass0"] == got["aclass1", "bclass1"] == 1.0 and len(got) == 8
    assert ("atype", "btype", "equivalent") in {(x.r, x.r2, x.op) for x in rules.verdicts(found.relations).collect()}


def test_few_ranks_suffice_or_all_are_taken(spark):
    r = random.Random(4)
    rows = [("t", "u", "r", f"h{r.randint(0, 3)}", "s", f"k{r.randint(0, 40)}", round(r.random(), 1) + 0.1, 0.5) for _ in range(150)] + [("v", "w", "r", "h", "s", f"k{i}", 0.5, 0.5) for i in range(30)]
    cp = spark.createDataFrame(sorted(set(rows)), "t string, t2 string, r string, h string, r2 string, h2 string, s_h double, s_r double").cache()
    plain = lambda df: sorted((x.t, x.n, str(x.a), str(x.b), round(x.hm_h, 9)) for x in df.collect())
    full = plain(rules.prefixes(rules.ranked_lists(cp, 4, None), 4))
    assert plain(rules.ranked_prefixes(cp, 4, first=3)) == plain(rules.ranked_prefixes(cp, 4)) == full


def test_list_functionality_by_enumeration(spark):
    r = random.Random(8)
    f = spark.createDataFrame(list({(f"h{r.randint(0, 9)}", r.choice("pqs"), f"t{r.randint(0, 12)}") for _ in range(110)} | {(f"x{i}", "one", f"t{i % 5}") for i in range(9)}), FACTS)
    f = cut(f)
    lists: dict = {}
    for x in fun.enumerate_lists(f, 3).collect():
        lists.setdefault(tuple((y.r, y.h) for y in x["items"]), set()).add(x.t)
    kinds = sorted({tuple(x[0] for x in k) for k in lists})
    want = {k: sum(1 for x in lists if tuple(y[0] for y in x) == k) / sum(len(v) for x, v in lists.items() if tuple(y[0] for y in x) == k) for k in kinds}
    needed = spark.createDataFrame([(list(k),) for k in kinds], "rels array<string>")
    got = {tuple(x.rels): x.f for x in fun.global_lists(f, needed, 3).collect()}
    assert got == pytest.approx(want)
    counted = {tuple(x.rels): x.n for x in fun.list_counts(f, needed).collect()}
    assert counted == pytest.approx({k: sum(len(v) for x, v in lists.items() if tuple(y[0] for y in x) == k) for k in kinds})
    asked = spark.createDataFrame([([{"r": a, "h": b} for a, b in k],) for k in lists], "items array<struct<r:string,h:string>>")
    here = {tuple((y.r, y.h) for y in x["items"]): x.f for x in fun.local_lists(f, asked).collect()}
    assert here == pytest.approx({k: 1 / len(v) for k, v in lists.items()})
    near = {tuple(x.rels): x.f for x in fun.global_lists(f, needed, 3, budget=50).collect()}
    assert all(abs(near[k] - want[k]) < 0.1 for k in kinds)


def many_names(spark):
    """Facts of 20 entities with 110 of 400 names each, 119,900 lists of two names, and the share of distinct ones."""
    r = random.Random(5)
    named = {f"t{i}": r.sample(range(400), 110) for i in range(20)}
    lists = [(x, y) for names in named.values() for x in names for y in names if x < y]
    return spark.createDataFrame([(t, "name", f'"{n:03}', "string", None) for t, names in named.items() for n in names], FACTS + ", kind string, x double"), len(set(lists)) / len(lists)


def test_functionality_in_a_run_is_exact_whatever_the_size(spark):
    f, want = many_names(spark)
    rows = align(f, f, identity=True, longest=2, rounds=1, theta_r=1.0, theta_e=-1.0).scores.select("why.f1", "why.f3", "why.a").collect()
    assert any(len(x.a) == 2 for x in rows) and all(x.f1 == x.f3 == pytest.approx(want, abs=1e-12) for x in rows if len(x.a) == 2)


def test_pairs_in_blocks_equal_enumeration(spark, monkeypatch):
    r = random.Random(9)
    rows = [(f"h{r.randint(0, 40)}", r.choice("pq"), f"t{r.randint(0, 6)}") for _ in range(400)]  # some facts twice
    f = cut(spark.createDataFrame(rows, FACTS))
    needed = spark.createDataFrame([(["p", "p"],), (["p", "q"],), (["q", "q"],)], "rels array<string>")
    told = lambda df: {tuple(x.rels): x.f for x in df.collect()}
    want = {}
    for a, b in (("p", "p"), ("p", "q"), ("q", "q")):
        met = [(h, h2) for h, x, t in rows for h2, y, t2 in rows if t == t2 and (x, y) == (a, b) and (a != b or h < h2)]
        want[a, b] = len(set(met)) / len(met)
    monkeypatch.setattr(fun, "PAIRS_A_ROW", 1e9)
    assert told(fun.global_lists(f, needed, 2)) == pytest.approx(want)
    monkeypatch.setattr(fun, "PAIRS_A_ROW", 0)
    monkeypatch.setattr(fun, "BLOCK", 60)
    assert cut(fun.dense_pairs(f, needed)).filter("left > 1 AND right > 1").count() == 3
    assert told(fun.global_lists(f, needed, 2)) == pytest.approx(want)
    block = pa.table({"k": [7] * 800, "same": [True] * 800, "side": [1] * 400 + [0] * 400, "h": [x[0] for x in rows] * 2, "t": [x[2] for x in rows] * 2}).to_batches()
    whole = fun._pair_block(block).to_pylist()
    monkeypatch.setattr(fun, "_PAIRS", 50)
    assert fun._pair_block(block).to_pylist() == whole


def test_best_strings_in_blocks_equal_proposed_ones(spark, monkeypatch):
    """Names that differ in a number only have common grams in their prefixes, so these would propose all pairs."""
    r = random.Random(3)
    a = spark.createDataFrame([(f"Supplier#{r.randint(0, 9999):09}",) for _ in range(150)] + [("é",), ("",), ("a long name of words",)], "s string")
    b = spark.createDataFrame([(f"supplier {r.randint(0, 9999):09}",) for _ in range(130)] + [("É",), ("",), ("a long name of worlds",), ("zzz",)], "s string")
    told = lambda: sorted((x.s, x.s2, round(x.sim, 8)) for x in literals.strings_similar(a, b).collect())
    monkeypatch.setattr(literals, "FEW_PAIRS", 0)
    monkeypatch.setattr(literals, "DEAR", 0)
    want = told()
    assert len(want) > 50
    for changes in ({"DEAR": 300}, {"FEW_PAIRS": 10**8}, {"STRINGS": 40}):
        for k, v in changes.items():
            monkeypatch.setattr(literals, k, v)
        assert told() == want
    plan = literals.strings_similar(a, b)._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "SortMergeJoin" not in plan  # no table of proposed pairs
    table = pa.table({"s": [x.s for x in a.collect()] + [x.s for x in b.collect()], "side": [1] * 153 + [0] * 134})
    table = table.append_column("text", pa.array([x.lower() for x in table.column("s").to_pylist()]))
    key = lambda t: {(x["s"], x["s2"], round(x["sim"], 8)) for x in t.to_pylist()}
    whole = key(literals._best_strings(table, 0.7))
    for name, value in (("_SIMS", 700), ("_KEPT", 10), ("_DENSE", 2)):
        monkeypatch.setattr(literals, name, value)
        assert key(literals._best_strings(table, 0.7)) == whole


def test_delta_equals_full_and_alternative_form(spark):
    tables = system(spark, [("min", ["a", "b"], "c"), ("hmean", ["c", "a"], "b"), ("mean", ["b", "c"], "d")], {"a": 0.8, "b": 0.3, "c": 0.1, "d": 0.0})
    one, two = ({x.var: x.value for x in fis.solve(*tables, epsilon=1e-3, rounds=12, delta=d).collect()} for d in (True, False))
    assert one == pytest.approx(two, abs=1e-2)
    assert {x.var: x.fixed for x in fis.normalised(tables[0], tables[2]).collect()} == {"a": True, "b": False, "c": False, "d": False}


def test_pairing_by_place(spark):
    cp = spark.createDataFrame([("t", "u", "a", "h1", "x", "k1", 1.0, 1.0), ("t", "u", "b", "h2", "y", "k2", 0.5, 1.0), ("v", "w", "a", "h1", "y", "k2", 1.0, 1.0), ("v", "w", "b", "h2", "x", "k1", 1.0, 1.0)], "t string, t2 string, r string, h string, r2 string, h2 string, s_h double, s_r double")
    assert {(x.t, len(x["items"])) for x in rules.positional_lists(cp).collect()} == {("t", 2)}


def test_tiny_twin(spark, tiny_dir):
    w = tw.twin(spark, tiny_dir, "tiny")
    found = align(w.a, w.b, longest=2, rounds=5).entities.select(F.col("t").alias("e"), F.col("t2").alias("e2"))
    assert metrics.prf(found, w.gold).first().f1 > 0.8


def test_baselines(spark, people):
    a, b = people
    assert {(r.t, r.t2) for r in baselines.exact_label(a, b, ("name",), ("nm",)).collect()} == {("p1", "q1"), ("p2", "q2")}
    assert {(r.t, r.t2) for r in baselines.name_similarity(a, b, ("name",), ("nm",)).collect()} == {("p1", "q1"), ("p2", "q2")}
    m = literals.matches(a, b, identity=True)
    p = baselines.probabilistic(facts.with_inverse(a), facts.with_inverse(b), m, 2)
    assert {(r.t, r.t2) for r in p.collect()} == {("p1", "q1"), ("p2", "q2")}
    s = baselines.sinkhorn(spark.createDataFrame([("a", "x", 0.9), ("a", "y", 0.5), ("b", "y", 0.6)], "t string, t2 string, score double"), 20).groupBy("t2").agg(F.sum("score").alias("s"))
    assert all(math.isclose(r.s, 1, abs_tol=1e-6) for r in s.collect())


def test_sampled_lists_are_looked_up_either_way(spark):
    draw = random.Random(3)
    rows = lambda tails, heads: spark.createDataFrame([(f"h{draw.randrange(heads)}", r, f"t{i}") for i in range(tails) for r in "uvw" for _ in range(2)], "h string, r string, t string").distinct()
    for f, n in ((rows(60, 4), 400), (rows(4, 40), 3)):  # popular heads, and tails with many facts
        f = cut(f)
        every = {tuple(r)[:4]: r.f for r in fun.of_head_pairs(f).collect()}
        needed = dict(draw.sample(sorted(every.items()), min(n, len(every))))
        asked = spark.createDataFrame([*needed], "r1 string, h1 string, r2 string, h2 string")
        assert {tuple(r)[:4]: r.f for r in fun.head_pairs_among(f, asked).select("r1", "h1", "r2", "h2", "f").collect()} == needed
        whole = {(r.r1, r.r2): r.f for r in fun.of_pairs(f).collect()}
        assert {(r.r1, r.r2): r.f for r in fun.pair_sampled(f, 1 << 20).collect()} == pytest.approx(whole)


def test_names_are_judged_before_entities_meet(spark):
    draw = random.Random(5)
    words = ["abcdef", "abcdeg", "abcdfg", "xyzuvw", "xyzuvx", "lonely"]
    side = lambda mark: [(f"{mark}{i}", f"{mark}name", '"' + w, "string", None) for i in range(30) for w in draw.sample(words, draw.choice((1, 1, 2)))]
    a, b = (spark.createDataFrame(side(m), KIND) for m in "ab")
    na, nb = baselines.names(a, ("aname",)), baselines.names(b, ("bname",)).withColumnsRenamed({"e": "e2", "s": "s2"})
    sims = literals.strings_similar(na.select("s"), nb.select(F.col("s2").alias("s")), 0.3, 1)
    pairs = na.join(sims, "s").join(nb, "s2").groupBy("e", "e2").agg(F.max("sim").alias("score"))
    found = baselines.name_similarity(a, b, ("aname",), ("bname",), 0.3)
    every = sorted(tuple(r) for r in rules.mutual_max(pairs, "e", "e2").select("e", "e2", "score").collect())
    assert every and sorted(tuple(r) for r in found.collect()) == every
    plan = found._jdf.queryExecution().sparkPlan().toString()
    assert "Window" not in plan.split("SortMergeJoin")[0]  # pairs of entities aren't shuffled to be ranked


def test_inverses_of_inverses(spark):
    f = facts.with_inverse(facts.with_inverse(triples(spark, "a r b")))
    assert {(r.h, r.r, r.t) for r in f.collect()} == {("a", "r", "b"), ("b", "r~", "a")}


def test_nulls_give_no_facts(spark, tmp_path):
    spark.createDataFrame([(1, "one", None, "k", 5, 1.5), (None, "two", "b", "k", 6, 2.5), (2, None, "b", None, None, None)], "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double").write.parquet(str(tmp_path / "part.parquet"))
    got = {(r.h, r.r, r.t) for r in facts.build(spark, str(tmp_path), PART).collect()}
    assert got == {("part/1", "label", '"one'), ("part/1", "kind", '"k'), ("part/1", "size", "#500"), ("part/1", "price", "#150"), ("part/2", "brand", '"b')}


def test_feature_propagation_counts_common_grams(spark):
    fact = "h string, r string, t string, kind string, x double"
    said = [("e", "common"), *[(f"p{i}", f"common {i:04d}") for i in range(210)], *[(f"s{i}", f"{i:04d} common") for i in range(210)]]
    side = lambda mark: spark.createDataFrame([(mark + e, "name", '"' + s, "string", None) for e, s in said], fact)
    got = baselines.feature_propagation(side("a"), side("b"), ("name",), ("name",), hops=0).collect()
    assert {r.t2 for r in got if r.t == "ae"} == {"be"}


def copies(spark, side, words, numbers):
    """People with a name and a town, several of them alike in all facts, and a friend that some have."""
    rng = random.Random(5)
    rows = []
    for i in range(24):
        kept = [r for r in ("name", "town", "age") if rng.random() < 0.8]
        for n in range(numbers):
            x = f"{side}{i}-{n}"
            rows += [(x, side + r, f'"{words} {r} {i % {"name": 8, "town": 3, "age": 4}[r]}', "string", None) for r in kept]
            if i % 6 == 0 and n < 2:
                rows.append((x, side + "friend", f"{side}{i + 1}-0", "person", None))
    return spark.createDataFrame(rows, KIND)


@pytest.mark.parametrize("changes", [{}, {"assign": "one", "seeded": True}])
def test_entities_alike_are_scored_once(spark, monkeypatch, changes):
    from graphweld.operators import alike as al

    a, b = cut(copies(spark, "a", "some", 2)), cut(copies(spark, "b", "some", 3))
    settings = dict(changes)
    seeds = spark.createDataFrame([("a3-1", "b3-2"), ("a7-0", "b7-0")], "t string, t2 string") if settings.pop("seeded", False) else None

    def run():
        found = align(a, b, seeds=seeds, longest=2, rounds=2, theta_e=-1.0, counters=True, **settings)
        pairs = lambda df: {(r.t, r.t2): (r.score, r.why) for r in df.collect()}
        relations = {(r.r, r.r2): (r.sub, r.sup, r.cov, r.cov2) for r in found.relations.collect()}
        return pairs(found.entities), pairs(found.scores), relations, [(h["lists"], h["pairs"], round(h["total"], 6)) for h in found.history]

    folded = run()
    assert al.alike(facts.with_inverse(a)).count() > 20
    monkeypatch.setattr(al, "FACTS", 0)  # nobody is alike
    assert al.alike(facts.with_inverse(a)).count() == 0
    plain = run()
    assert folded[1:] == plain[1:] and folded[0] == plain[0] and folded[0]


def test_lists_of_tails_with_few_and_many_facts(spark, monkeypatch):
    rng = random.Random(3)
    rows = {(f"h{rng.randrange(5)}", f"r{rng.randrange(3)}", f"t{t}") for t in range(30) for _ in range(12 if t % 3 == 0 else 3)}
    f = cut(spark.createDataFrame(sorted(rows), FACTS))
    item = lambda i: F.struct(F.col(f"r{i}").alias("r"), F.col(f"h{i}").alias("h"))
    items = cut(fun.of_head_pairs(f).select(F.array(item(1), item(2)).alias("items")))
    want = {str(r["items"]): r.f for r in fun.local_lists(f, items).collect()}
    for few in (0, 4, 100):
        monkeypatch.setattr(fun, "FEW", few)
        assert {str(r["items"]): r.f for r in fun.LocalLists(f, 2).of(items).collect()} == want


def test_pairs_with_the_same_counterparts_are_one(spark, monkeypatch):
    from graphweld.operators import shared as sh

    draw = random.Random(11)
    side = lambda mark, n: cut(spark.createDataFrame(sorted({(f"{mark}h{draw.randrange(4)}", mark + draw.choice("rs"), f"{mark}t{draw.randrange(n)}") for _ in range(3 * n)}), FACTS))
    a, b = side("a", 20), side("b", 25)
    heads = spark.createDataFrame([(f"ah{i}", f"bh{(i + d) % 4}", s) for i in range(4) for d, s in ((0, 1.0), (1, 0.5), (2, 0.0))], "h string, h2 string, s double")
    sims = spark.createDataFrame([("ar", "br", 1.0), ("as", "bs", 0.5), ("ar", "bs", 0.2), ("as", "br", 0.0)], "r string, r2 string, s_r double")
    row = lambda x: (x.r, x.h, x.r2, x.h2, x.s_h, x.s_r)
    for relations in (None, sims):
        cp = rules.counterparts(a, b, heads, relations)
        want: dict = {}
        for x in cp.collect():
            want.setdefault((x.t, x.t2), set()).add(row(x))
        for most in (256, 4):
            monkeypatch.setattr(sh, "MOST", most)
            found = sh.SharedPairs(sh.Facts(a), sh.Facts(b), heads, relations, cut(cp.select("t", "t2").distinct()))
            sets: dict = {}
            for x in found.counterparts(relations, 0.1).collect():
                sets.setdefault((x.t, x.t2), set()).add(row(x))
            alone = set() if found.large is None else {(x.t, x.t2) for x in found.large.collect()}
            assert bool(alone) == (most == 4) and all(sets[k] == want[k] for k in sets)
            stands = {(x.t, x.t2): (x.k, x.k2) for x in found.rows.collect()}
            assert stands.keys() | alone == want.keys() and not stands.keys() & alone and set(stands.values()) == set(sets)
            assert all(want[k] == want[v] for k, v in stands.items()) and len({frozenset(v) for v in sets.values()}) == len(sets) < len(stands)
            every = found.spread(cp.groupBy("t", "t2").agg(F.count(F.lit(1)).alias("n")), "n").collect()
            assert {(x.t, x.t2): x.n for x in every} == {k: len(v) for k, v in want.items()}


def test_numbers_keep_the_order_of_names(spark):
    from graphweld.operators.numbered import named, numbered, numbers

    f = spark.createDataFrame([("!x", "r", "10"), ("b", "r", '"b'), ("9", "r", "#9"), ("b", "r", "~"), ("Z", "r", "@d")], FACTS)
    n = cut(numbers(f, spark.createDataFrame([("seed",)], "t string")))
    ids = {x.name: x.id for x in n.collect()}
    assert sorted(ids) == sorted(ids, key=ids.get) and {k for k, i in ids.items() if i % 2} == {'"b', "#9", "@d"} and len(ids) == 10
    told = numbered(f, ("h", n), ("t", n))
    assert {(x.h, x.t) for x in told.filter(facts.is_literal(F.col("t"))).collect()} == {(ids["b"], ids['"b']), (ids["9"], ids["#9"]), (ids["Z"], ids["@d"])}
    assert {tuple(x) for x in named(told, ("h", n), ("t", n)).collect()} == {tuple(x) for x in f.collect()}
