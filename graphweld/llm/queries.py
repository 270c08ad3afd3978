"""The registered queries of the training-data operators, and their DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from graphweld.llm import html_mincut, iso_media, license_join, mixing, phrase_fingerprint, quality_bayes, simhash_bk, suffix_dedup, token_packing, url_rules
from graphweld.llm.common import table


def op1_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_mincut.extract(table(spark, sf_dir, "pages"))


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).drop("mix_key")


def op3_simhash_bk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_bk.cluster(table(spark, sf_dir, "documents"))


def op4_phrase_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return phrase_fingerprint.compare_edited(table(spark, sf_dir, "documents"))


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_join.scan(table(spark, sf_dir, "documents"))


def op6_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return iso_media.store(table(spark, sf_dir, "documents"))


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.strip(table(spark, sf_dir, "documents"))


def op8_pack_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_packing.pack(table(spark, sf_dir, "documents"))


def op9_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_rules.judge(table(spark, sf_dir, "pages"))


def op10_quality_bayes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_bayes.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_main_text, op2_mix_sources, op3_simhash_bk, op4_phrase_fingerprints, op5_license_scan, op6_media_columns, op7_suffix_dedup, op8_pack_tokens, op9_url_rules, op10_quality_bayes]
    return {f.__name__: f for f in found}


_RULE_ROWS = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in url_rules.RULES)

#: Fixed values of XXH64.
_P1, _P2, _P3, _P4, _P5 = 11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261


def _mod(x: str) -> str:
    return f"(({x}) % {1 << 64}::UHUGEINT)"


def _turn(x: str, bits: int) -> str:
    """x turned left within 64 bits."""
    return f"({_mod(f'{x} * {1 << bits}::UHUGEINT')} + {x} // {1 << (64 - bits)}::UHUGEINT)"


def _lane(acc: str, x: str) -> str:
    return _mod(f"{_turn(_mod(f'{acc} + {_mod(f"{x} * {_P2}::UHUGEINT")}'), 31)} * {_P1}::UHUGEINT")


def _step(h: str, x: str, turn: int, factor: int, plus: int) -> str:
    return _mod(f"{_turn(f'xor({h}, {x})', turn)} * {factor}::UHUGEINT + {plus}")


def _hash_sql(seed: int) -> str:
    """Common tables that end in ``hashed``: shingle and its XXH64 as h, for the distinct rows of a table ``shingles`` (shingle)."""
    number = lambda a, b: f"list_reduce(list_reverse(bytes[{a}:{b}]), lambda x, y: x * 256 + y)"
    starts = [(seed + _P1 + _P2) % (1 << 64), (seed + _P2) % (1 << 64), seed, (seed - _P1) % (1 << 64)]
    accs = ", ".join(f"list_reduce([{v}::UHUGEINT] || list_transform(range(n // 32), lambda i: lanes[4 * i + {j}]), lambda x, y: {_lane('x', 'y')}) AS v{j}" for j, v in enumerate(starts, 1))
    long = _mod(" + ".join(_turn(f"v{j}", t) for j, t in enumerate((1, 7, 12, 18), 1)))
    mix = lambda h, v: _mod(f"xor({h}, {_lane('0::UHUGEINT', v)}) * {_P1}::UHUGEINT + {_P4}::UHUGEINT")
    return f"""
        bytes AS (SELECT shingle, strlen(shingle) AS n, list_transform(range(strlen(shingle)), lambda i: ('0x' || substr(hex(encode(shingle)), 2 * i + 1, 2))::INT::UHUGEINT) AS bytes FROM (SELECT DISTINCT shingle FROM shingles)),
        lanes AS (SELECT *, list_transform(range(n // 8), lambda k: {number("8 * k + 1", "8 * k + 8")}) AS lanes FROM bytes),
        accs AS (SELECT *, {accs} FROM lanes),
        heads AS (SELECT *, {long} AS w FROM accs),
        started AS (SELECT *, {_mod(f"CASE WHEN n < 32 THEN {(seed + _P5) % (1 << 64)}::UHUGEINT ELSE list_reduce([w, v1, v2, v3, v4], lambda x, y: {mix('x', 'y')}) END + n::UHUGEINT")} AS h0 FROM heads),
        eights AS (SELECT *, list_reduce([h0] || lanes[4 * (n // 32) + 1 :], lambda x, y: {_step("x", _lane("0::UHUGEINT", "y"), 27, _P1, _P4)}) AS h1 FROM started),
        fours AS (SELECT *, CASE WHEN n % 8 >= 4 THEN {_step("h1", _mod(f"{number('n - n % 8 + 1', 'n - n % 8 + 4')} * {_P1}::UHUGEINT"), 23, _P2, _P3)} ELSE h1 END AS h2 FROM eights),
        ones AS (SELECT *, list_reduce([h2] || bytes[n - n % 4 + 1 :], lambda x, y: {_step("x", _mod(f"y * {_P5}::UHUGEINT"), 11, _P1, 0)}) AS h3 FROM fours),
        first_mix AS (SELECT shingle, {_mod(f"xor(h3, h3 // {1 << 33}::UHUGEINT) * {_P2}::UHUGEINT")} AS h4 FROM ones),
        second_mix AS (SELECT shingle, {_mod(f"xor(h4, h4 // {1 << 29}::UHUGEINT) * {_P3}::UHUGEINT")} AS h5 FROM first_mix),
        hashed AS MATERIALIZED (SELECT shingle, xor(h5, h5 // {1 << 32}::UHUGEINT)::UBIGINT AS h FROM second_mix)"""


ORACLE: dict[str, str] = {
    "op3_simhash_bk": f"""
        WITH RECURSIVE docs AS (
            SELECT row_number() OVER (ORDER BY doc_id, text) AS k, doc_id,
                   regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
        shingles AS MATERIALIZED (SELECT k, unnest(list_transform(range(1, greatest(len(w) - 2, 2)), lambda i: array_to_string(w[i : i + 3], ' '))) AS shingle FROM docs WHERE len(w) > 0),
        {_hash_sql(42)},
        counted AS (SELECT k, h, count(*) AS c FROM shingles JOIN hashed USING (shingle) GROUP BY k, h),
        bits AS (SELECT k, b, sum(c * ((h >> b::UBIGINT) & 1::UBIGINT)::INT) AS ones, sum(c) AS n FROM counted, range(64) t(b) GROUP BY k, b),
        majority AS (SELECT k, bit_or(CASE WHEN 2 * ones > n THEN 1::UHUGEINT << b::UHUGEINT ELSE 0::UHUGEINT END)::UBIGINT AS fp FROM bits GROUP BY k),
        marked AS MATERIALIZED (SELECT doc_id, coalesce(fp, 0::UBIGINT) AS fp FROM docs LEFT JOIN majority USING (k)),
        prints AS MATERIALIZED (SELECT fp, min(doc_id) AS first, count(*) AS copies FROM marked GROUP BY fp),
        links AS MATERIALIZED (SELECT a.fp AS a, b.fp AS b FROM prints a, prints b WHERE a.fp <> b.fp AND bit_count(xor(a.fp, b.fp)::HUGEINT) <= 4),
        reach(a, b) AS (SELECT fp, fp FROM prints UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b),
        least_id AS (SELECT a, min(first) AS component_id FROM reach JOIN prints ON fp = b GROUP BY a)
        SELECT doc_id, lpad(lower(hex(fp)), 16, '0') AS fingerprint, component_id, copies FROM marked JOIN prints USING (fp) JOIN least_id ON a = fp""",
    # the level is that of the first source, by the level at which it fills up, that isn't full at it
    "op2_mix_sources": """
        WITH docs AS (
            SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::BIGINT AS size,
                   ('0x' || left(md5(concat_ws('|', 20, doc_id, text)), 15))::BIGINT AS k FROM documents),
        sums AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS o FROM docs GROUP BY source),
        per AS (SELECT *, [1.0, 2.0, 3.0][((o - 1) % 3 + 1)::INT]::DOUBLE AS w, 3.0::DOUBLE * source_size AS cap FROM sums),
        tried AS (
            SELECT p.o, p.w, p.cap, ((SELECT sum(source_size) FROM per) - coalesce(sum(q.cap), 0)) / ((SELECT sum(w) FROM per) - coalesce(sum(q.w), 0)) AS level
            FROM per p LEFT JOIN per q ON (q.cap / q.w, q.o) < (p.cap / p.w, p.o) GROUP BY p.o, p.w, p.cap),
        found AS (SELECT level FROM tried WHERE cap >= level * w ORDER BY cap / w, o LIMIT 1),
        goal AS (SELECT source, source_size, coalesce(least(cap, (SELECT level FROM found) * w), cap) AS target FROM per),
        runs AS (
            SELECT d.*, g.source_size, g.target, round(g.target)::BIGINT AS budget,
                   coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY k, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
            FROM docs d JOIN goal g ON d.source IS NOT DISTINCT FROM g.source),
        cuts AS (SELECT *, CASE WHEN source_size > 0 THEN budget // source_size ELSE 0 END AS epochs FROM runs)
        SELECT doc_id, size, source_size, target, (epochs * size + greatest(0, least(size, budget - epochs * source_size - before)))::BIGINT AS taken FROM cuts""",
    # all windows of 200 bytes, as hexadecimal digits, cut from pieces of 399 bytes; then runs of starts at most 200 apart
    "op7_suffix_dedup": """
        WITH texts AS MATERIALIZED (SELECT row_number() OVER (ORDER BY doc_id, text) AS k, doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
        pieces AS (SELECT k, 200 * j AS off, substr(x, 400 * j + 1, 798) AS y FROM (SELECT k, x, unnest(range((len(x) // 2 + 199) // 200)) AS j FROM texts)),
        windows AS MATERIALIZED (SELECT k, off + o AS a, md5_number(substr(y, 2 * o + 1, 400)) AS w FROM (SELECT k, off, y, unnest(range(len(y) // 2 - 199)) AS o FROM pieces WHERE len(y) >= 400)),
        hits AS (SELECT k, a FROM windows WHERE w IN (SELECT w FROM windows GROUP BY w HAVING count(*) > 1)),
        marked AS (SELECT k, a, coalesce(a - lag(a) OVER (PARTITION BY k ORDER BY a) > 200, true) AS fresh FROM hits),
        numbered AS (SELECT k, a, sum(fresh::INT) OVER (PARTITION BY k ORDER BY a) AS run FROM marked),
        runs AS (SELECT k, run, min(a) AS a, max(a) + 200 AS b FROM numbered GROUP BY k, run),
        gaps AS (
            SELECT k, coalesce(lag(b) OVER (PARTITION BY k ORDER BY a), 0) AS a, a AS b FROM runs
            UNION ALL SELECT k, max(b), NULL FROM runs GROUP BY k UNION ALL SELECT k, 0, NULL FROM texts WHERE k NOT IN (SELECT k FROM runs)),
        rests AS (SELECT k, string_agg(CASE WHEN b IS NULL THEN substr(x, 2 * a + 1) ELSE substr(x, 2 * a + 1, 2 * (b - a)) END, '' ORDER BY a, b NULLS LAST) AS rest FROM gaps JOIN texts USING (k) GROUP BY k)
        SELECT doc_id, (len(x) // 2)::BIGINT AS n_bytes, ((len(x) - len(rest)) // 2)::BIGINT AS n_removed, coalesce(n, 0)::BIGINT AS n_spans, sha256(unhex(rest)) AS kept_sha256
        FROM texts JOIN rests USING (k) LEFT JOIN (SELECT k, count(*) AS n FROM runs GROUP BY k) USING (k)""",
    "op9_url_rules": f"""
        WITH rules(verdict, rule_host, rule_path) AS (VALUES {_RULE_ROWS}),
        parts AS (
            SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
        urls AS (
            SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
                   regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM parts),
        hits AS (
            SELECT u.page_id, r.rule_host || r.rule_path AS rule, r.verdict,
                   row_number() OVER (PARTITION BY u.page_id ORDER BY length(r.rule_host || r.rule_path) DESC) AS n
            FROM urls u JOIN rules r ON (u.host = r.rule_host OR ends_with(u.host, '.' || r.rule_host)) AND starts_with(u.path, r.rule_path))
        SELECT u.page_id, coalesce(u.host, '') AS host, coalesce(u.path, '') AS path, h.rule, coalesce(h.verdict, 'allow') AS verdict
        FROM urls u LEFT JOIN hits h ON h.page_id = u.page_id AND h.n = 1""",
}
