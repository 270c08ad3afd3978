"""Spark against DuckDB on the smallest tables, plans, sources and streams."""

import duckdb
import pytest

import __spark_entry__ as entry
from graphweld.operators import facts
from graphweld.operators import functionality as fun
from graphweld.operators import literals
from graphweld.plans.fact_rules import PART
from graphweld.sources import triples
from graphweld.streaming import streams
from graphweld.workloads import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUICK = [
    "kg_facts_part", "kg_facts_full", "kg_nodes_by_kind", "twin_facts_tiny", "fun_local", "list_enum_2", "fun_list_global_2", "list_pairs_binomial", "fun_list_on_demand", "fuzzify_price", "mamdani_cap_combine",
    "agg_hmean", "agg_product", "lit_numbers_band", "lit_top1", "counterparts_part", "candidates_structural", "entity_round0", "align_two_rounds", "metrics_prf", "explain_best_pair", "sql_fn_hmean", "base_probabilistic_round1", "join_asof", "join_interval",
    "agg_grouping_sets", "win_running_hmean", "doc_benchmark_containment", "page_facts", "event_json_facts", "udtf_lists", "stream_functionality", "stream_sessions", "stream_dedup", "stream_late_rows",
]


def plain(v):
    if isinstance(v, float):
        return f"{v:.5g}"
    return "~" if v is None else str(v)


@pytest.fixture(scope="module")
def duck(tiny_dir):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tiny_dir}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", QUICK)
def test_same_as_sql(spark, duck, tiny_dir, name):
    df = registry.queries()[name](spark, tiny_dir)
    want = duck.sql(registry.oracle_sql()[name])
    columns = sorted(df.columns)
    assert columns == sorted(want.columns)
    order = [want.columns.index(c) for c in columns]
    assert sorted(tuple(map(plain, r)) for r in df.select(*columns).collect()) == sorted(tuple(plain(r[i]) for i in order) for r in want.fetchall())


@pytest.mark.parametrize("name", ["twin_gold_entities", "twin_dangling"])
def test_gold_with_repeated_opaque_names(spark, tiny_dir, tmp_path, name):
    """Keys over 1000003 share their names in the second graph with smaller ones."""
    connection = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"):
        moved = {"orders": "o_orderkey", "lineitem": "l_orderkey"}.get(t)
        copy = f"UNION ALL SELECT * REPLACE ({moved} + 1000003 AS {moved}) FROM '{tiny_dir}/{t}.parquet'" if moved else ""
        connection.sql(f"COPY (SELECT * FROM '{tiny_dir}/{t}.parquet' {copy}) TO '{tmp_path}/{t}.parquet'")
        connection.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet'")
    want = connection.sql(registry.oracle_sql()[name])
    got = registry.queries()[name](spark, str(tmp_path)).select(*want.columns).collect()
    assert sorted(map(tuple, got)) == sorted(want.fetchall())


@pytest.mark.parametrize("name", ["twin_gold_relations", "fis_violations", "fis_minimality"])
def test_of_the_tables_and_same_as_sql(spark, duck, tiny_dir, name):
    df = registry.queries()[name](spark, tiny_dir)
    want = duck.sql(registry.oracle_sql()[name])
    rows = want.fetchall()
    assert sorted(tuple(map(plain, r)) for r in df.select(*want.columns).collect()) == sorted(tuple(map(plain, r)) for r in rows)
    assert rows and (name == "twin_gold_relations" or "part.parquet" in " ".join(df.inputFiles()))


def test_close_numbers_equal_brute_force(spark):
    rows = [("a", 0.0), ("b", 5.0), ("b", 5.0 * (1 + 4e-10)), ("c", -5.0), ("d", 5.0 * (1 + 8e-10)), ("d", 7.0), ("e", 7.0), ("f", None), ("g", 5.0 * (1 + 2e-9))]
    a = spark.createDataFrame(rows, "n string, x double")
    found = literals.numbers_close(a, a.withColumnsRenamed({"n": "n2", "x": "x2"}))
    want = {(n, m) for n, x in rows for m, y in rows if None not in (x, y) and abs(x - y) <= 1e-9 * max(abs(x), abs(y))}
    assert sorted(map(tuple, found.collect())) == sorted(want)
    plan = found._jdf.queryExecution().optimizedPlan().toString().splitlines()
    assert plan[0].startswith("Union")  # pairs of ids with one value aren't made distinct by a shuffle


def test_lsh_best_equal_all_pairs_that_meet(spark):
    """With one key for all vectors every pair meets, so the best is that of the exact search; vectors are shuffled by key only."""
    v = [(i, [float((i * 7 + j * j) % 11) - 5.0 + (j == i % 8) for j in range(8)]) for i in range(40)]
    a = spark.createDataFrame(v, "id long, v array<double>")
    b = a.withColumnsRenamed({"id": "id2", "v": "v2"})
    found = literals.vector_lsh(a, b, dimension=8, tables=2, bits=0)
    want = literals.vector_top1(a, b)
    tell = lambda df: sorted((r.id, r.id2, round(r.sim, 9)) for r in df.collect())
    assert tell(found) == tell(want)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert not [x for x in plan.splitlines() if "hashpartitioning(id" in x and "id2" in x]


def test_lsh_pairs_are_no_rows_and_blocks_change_nothing(spark, monkeypatch):
    v = [(i, [float((i % 30 * 7 + j * j) % 11) - 5.0 + (j == i % 8) for j in range(8)]) for i in range(120)] + [(200, None), (201, [0.0] * 8), (202, [1.0, 2.0]), (203, [])]  # vectors of 120 ids are 30 or so, so there are ties
    a = spark.createDataFrame(v, "id long, v array<double>").filter("id <> 203")
    b = spark.createDataFrame(v, "id2 long, v2 array<double>")
    brute = {}
    for i, x in v:
        for j, y in v:
            if x and y and len(x) == len(y) and any(x) and any(y):
                dot = sum(p * q for p, q in zip(x, y, strict=True))
                sim = round(dot / (sum(p * p for p in x) * sum(q * q for q in y)) ** 0.5, 9)
                if sim >= 0.7 and (i not in brute or (-sim, j) < brute[i]):
                    brute[i] = (-sim, j)
    want = sorted((i, j, -sim) for i, (sim, j) in brute.items())
    told = lambda **c: sorted((r.id, r.id2, round(r.sim, 9)) for r in literals.vector_lsh(a, b, dimension=8, **c).collect())
    assert told(tables=2, bits=0) == want
    some = told(tables=3, bits=2)
    assert 0 < len(some)
    monkeypatch.setattr(literals, "VECTORS", 7)  # a key is dealt over several blocks
    assert told(tables=2, bits=0) == want and told(tables=3, bits=2) == some
    plan = literals.vector_lsh(a, b, dimension=8)._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "SortMergeJoin" not in plan


def test_dense_twin_runs_until_settled(monkeypatch):
    from graphweld.plans.engine import Params
    from graphweld.workloads import more_queries

    monkeypatch.setattr(more_queries, "quality", lambda spark, d, twin, method, **changes: (twin, changes))
    twin, changes = registry.queries()["align_wide_dense15"](None, "")
    assert twin == "dense15" and changes["rounds"] > Params().rounds and changes["longest"] == 2


def test_facts_are_not_broadcast(spark, tiny_dir):
    f = facts.with_inverse(facts.build(spark, tiny_dir, PART))
    for df in (fun.pairs(f), fun.pair_counts(f), fun.enumerate_lists(f, 2), fun.pair_mean_local(f)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


@pytest.mark.parametrize("name", ["fis_violations", "fis_minimality"])
def test_systems_of_parts_are_not_broadcast(spark, tiny_dir, name):
    plan = registry.queries()[name](spark, tiny_dir)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Broadcast" not in plan


@pytest.mark.parametrize("mode", ["append", "complete"])
def test_drained_streams_are_written_tables(spark, tmp_path, mode):
    rows = spark.createDataFrame([(i, f"k{i % 3}") for i in range(30)], "n int, k string")
    for part in range(3):  # three micro-batches
        rows.filter(f"n % 3 = {part}").coalesce(1).write.parquet(str(tmp_path / "in"), mode="append")
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    found = streams.drain(stream if mode == "append" else stream.groupBy("k").count(), mode)
    want = rows.collect() if mode == "append" else [(f"k{i}", 10) for i in range(3)]
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, want))
    assert found.inputFiles()  # read from files, not from rows that the driver holds
    (tmp_path / "none").mkdir()
    nothing = spark.readStream.schema(rows.schema).parquet(str(tmp_path / "none"))
    assert streams.drain(nothing if mode == "append" else nothing.groupBy("k").count(), mode).count() == 0


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(registry.queries()) > 90


def test_filters_and_columns_reach_the_scan(spark, tiny_dir):
    plan = facts.build(spark, tiny_dir, PART[:1])._jdf.queryExecution().executedPlan().toString()
    assert "p_retailprice" not in plan and "p_name" in plan


def test_triple_sources(spark, tmp_path):
    (tmp_path / "a.nt").write_text('<a> <knows> <b> .\n<a> <age> "7"^^<http://www.w3.org/2001/XMLSchema#integer> .\n# note\nbroken line\n<a> <name> "A \\"x\\""@en .\n<a> <knows> <b> .\n')
    good, bad = triples.ntriples(spark, str(tmp_path / "a.nt"))
    assert {(r.h, r.r, r.t, r.kind) for r in good.collect()} == {("a", "knows", "b", "instance"), ("a", "age", "#7", "number"), ("a", "name", '"A \\"x\\"', "string")}
    assert [r.value for r in bad.collect()] == ["broken line"]
    (tmp_path / "b.tsv").write_text("a\tr\tb\na\tr\tb\nx\ty\n")
    assert triples.tsv(spark, str(tmp_path / "b.tsv")).count() == 1
    spark.dataSource.register(triples.FactSource)
    assert spark.read.format("facts").option("n", "10").option("parts", "3").load().count() == 10
    triples.write_by_relation(spark.createDataFrame([("a", "r", "b"), ("a", "s", "b")], "h string, r string, t string"), str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).filter("r = 'r'").count() == 1
