"""SQL pieces of the oracles, written from the definitions and not from the plans."""

from __future__ import annotations

from graphweld.operators.twin import sql as twin_sql
from graphweld.plans.fact_rules import FactRule, rules_sql

LIT = "substr({}, 1, 1) IN ('\"', '#', '@')"


def facts_sql(rules: tuple[FactRule, ...]) -> str:
    """CTEs base, facts (h, r, t, kind, x) and closed (h, r, t)."""
    return f"""base AS MATERIALIZED ({rules_sql(rules)}),
facts AS (SELECT hk || '/' || hid AS h, r, CASE tk WHEN 'string' THEN '"' || tid WHEN 'number' THEN '#' || tid WHEN 'date' THEN '@' || tid ELSE tk || '/' || tid END AS t, tk AS kind, x FROM base),
closed AS MATERIALIZED (SELECT h, r, t FROM facts UNION ALL SELECT t, r || '~', h FROM facts)"""


def closed_sql(name: str) -> str:
    """Twin CTEs with a and b closed under inverses."""
    return f"""{twin_sql(name)},
a AS MATERIALIZED (SELECT h, r, t FROM fa UNION ALL SELECT t, r || '~', h FROM fa),
b AS MATERIALIZED (SELECT h AS h2, r AS r2, t AS t2 FROM fb UNION ALL SELECT t, r || '~', h FROM fb)"""


def pair_tables(facts: str, prefix: str) -> str:
    """CTEs of functionality: {prefix}r (r, f), {prefix}rh (r, h, f), {prefix}p (r1, r2, f), {prefix}ph (r1, h1, r2, h2, f)."""
    return f"""{prefix}r AS (SELECT r, count(DISTINCT h) * 1.0 / count(*) AS f FROM {facts} GROUP BY r),
{prefix}rh AS (SELECT r, h, 1.0 / count(*) AS f FROM {facts} GROUP BY r, h),
{prefix}pairs AS MATERIALIZED (SELECT x.r AS r1, x.h AS h1, y.r AS r2, y.h AS h2, x.t FROM {facts} x JOIN {facts} y ON x.t = y.t AND (x.r, x.h) < (y.r, y.h)),
{prefix}ph AS (SELECT r1, h1, r2, h2, 1.0 / count(*) AS f FROM {prefix}pairs GROUP BY ALL),
{prefix}p AS (SELECT r1, r2, count(DISTINCT (h1, h2)) * 1.0 / count(*) AS f FROM {prefix}pairs GROUP BY r1, r2)"""


def grams_sql(text: str) -> str:
    return f"unnest([substr('^' || {text} || '$', i, 3) FOR i IN generate_series(1, greatest(1, length({text})))])"


def string_sims(theta: float = 0.7, text: str = "lower(s)", left: str = "fa", right: str = "fb") -> str:
    """CTE sims (s, s2, sim) of strings by 3-gram cosine, before the best are chosen."""
    one = lambda f: f"""SELECT s, g, count(*) * 1.0 AS c FROM (SELECT s, {grams_sql(text)} AS g FROM (SELECT DISTINCT substr(t, 2) AS s FROM {f} WHERE kind = 'string')) GROUP BY s, g"""
    return f"""ga AS ({one(left)}), gb AS ({one(right)}),
na AS (SELECT s, sqrt(sum(c * c)) AS n FROM ga GROUP BY s), nb AS (SELECT s, sqrt(sum(c * c)) AS n FROM gb GROUP BY s),
allsims AS (SELECT ga.s, gb.s AS s2, least(1.0, round(sum((ga.c / na.n) * (gb.c / nb.n)), 9)) AS sim FROM ga JOIN gb USING (g) JOIN na ON na.s = ga.s JOIN nb ON nb.s = gb.s GROUP BY ga.s, gb.s),
sims AS (SELECT * FROM allsims WHERE sim >= {theta})"""


BEST = "best AS (SELECT s, s2, sim FROM (SELECT *, rank() OVER (PARTITION BY s ORDER BY sim DESC) AS k, rank() OVER (PARTITION BY s2 ORDER BY sim DESC) AS k2 FROM sims) WHERE k = 1 OR k2 = 1)"
NUMBERS = """nums AS (SELECT DISTINCT x.t AS n, y.t AS n2 FROM (SELECT DISTINCT t, x FROM fa WHERE kind = 'number') x JOIN (SELECT DISTINCT t, x FROM fb WHERE kind = 'number') y
  ON y.x BETWEEN least(x.x * (1 - 2e-9), x.x * (1 + 2e-9)) AND greatest(x.x * (1 - 2e-9), x.x * (1 + 2e-9)) AND abs(x.x - y.x) <= 1e-9 * greatest(abs(x.x), abs(y.x)))"""


def literal_matches(theta: float = 0.7, text: str = "lower(s)") -> str:
    """CTE lm (h, h2, s): all literal matches of a twin."""
    return f"""{string_sims(theta, text)}, {BEST}, {NUMBERS},
lm AS MATERIALIZED (SELECT '"' || s AS h, '"' || s2 AS h2, sim AS s FROM best UNION ALL SELECT n, n2, 1.0 FROM nums
  UNION ALL SELECT DISTINCT fa.t, fb.t, 1.0 FROM fa JOIN fb ON fa.t = fb.t AND fa.kind = 'date' AND fb.kind = 'date')"""


def cp_sql(heads: str, relations: str | None, tag: str) -> str:
    """CTE cp{tag}."""
    s_r, join = ("0.1", "") if relations is None else ("rel.s_r", f"JOIN {relations} rel ON rel.r = a.r AND rel.r2 = b.r2 AND rel.s_r > 0")
    return f"""cp{tag} AS MATERIALIZED (SELECT a.t, b.t2, a.r, a.h, b.r2, b.h2, m.s AS s_h, cast({s_r} as double) AS s_r FROM {heads} m JOIN a ON a.h = m.h JOIN b ON b.h2 = m.h2 {join}
  WHERE m.s > 0 AND NOT {LIT.format('a.t')} AND NOT {LIT.format('b.t2')})"""


def candidates_sql(tag: str) -> str:
    return f"""cand{tag} AS MATERIALIZED (SELECT t, t2, n FROM (SELECT t, t2, count(DISTINCT (r, h)) AS n, rank() OVER (PARTITION BY t ORDER BY count(DISTINCT (r, h)) DESC) AS k FROM cp{tag} GROUP BY t, t2) WHERE k = 1)"""


def entity_sql(tag: str, longest: int = 2, minimum: bool = False, search: bool = True) -> str:
    """CTEs up to sc{tag} (t, t2, n, score per list) and best score per pair es{tag} (t, t2, score)."""
    keep = f"SEMI JOIN cand{tag} USING (t, t2)" if search else ""
    mean = (lambda c: f"least(f.{c}, g.{c})") if minimum else (lambda c: f"2 / (1 / f.{c} + 1 / g.{c})")
    two = f"""UNION ALL SELECT f.t, f.t2, 2, round(least({mean('s_h')}, {mean('s_r')}, p1.f, p2.f, q1.f, q2.f), 9) FROM first{tag} f JOIN second{tag} g USING (t, t2)
  JOIN ap p1 ON p1.r1 = least(f.r, g.r) AND p1.r2 = greatest(f.r, g.r)
  JOIN aph p2 ON (p2.r1, p2.h1) = (CASE WHEN (f.r, f.h) < (g.r, g.h) THEN (f.r, f.h) ELSE (g.r, g.h) END) AND (p2.r2, p2.h2) = (CASE WHEN (f.r, f.h) < (g.r, g.h) THEN (g.r, g.h) ELSE (f.r, f.h) END)
  JOIN bp q1 ON q1.r1 = least(f.r2, g.r2) AND q1.r2 = greatest(f.r2, g.r2)
  JOIN bph q2 ON (q2.r1, q2.h1) = (CASE WHEN (f.r2, f.h2) < (g.r2, g.h2) THEN (f.r2, f.h2) ELSE (g.r2, g.h2) END) AND (q2.r2, q2.h2) = (CASE WHEN (f.r2, f.h2) < (g.r2, g.h2) THEN (g.r2, g.h2) ELSE (f.r2, f.h2) END)"""
    return f"""ranked{tag} AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY t, t2 ORDER BY least(s_h, s_r) DESC, s_h DESC, r, h, r2, h2) AS k FROM cp{tag} {keep}),
first{tag} AS (SELECT * FROM ranked{tag} WHERE k = 1),
second{tag} AS (SELECT g.* FROM ranked{tag} g JOIN first{tag} f USING (t, t2) WHERE NOT (g.r = f.r AND g.h = f.h) AND NOT (g.r2 = f.r2 AND g.h2 = f.h2) QUALIFY row_number() OVER (PARTITION BY g.t, g.t2 ORDER BY g.k) = 1),
sc{tag} AS MATERIALIZED (SELECT f.t, f.t2, 1 AS n, round(least(f.s_h, f.s_r, x.f, y.f, z.f, w.f), 9) AS score FROM first{tag} f
  JOIN ar x ON x.r = f.r JOIN arh y ON y.r = f.r AND y.h = f.h JOIN br z ON z.r = f.r2 JOIN brh w ON w.r = f.r2 AND w.h = f.h2 {two if longest > 1 else ''}),
es{tag} AS MATERIALIZED (SELECT t, t2, max(score) AS score FROM sc{tag} GROUP BY t, t2)"""


def mutual_sql(scores: str, name: str) -> str:
    return f"{name} AS MATERIALIZED (SELECT t, t2, score FROM (SELECT *, max(score) OVER (PARTITION BY t) AS m, max(score) OVER (PARTITION BY t2) AS m2 FROM {scores}) WHERE score >= m AND score >= m2)"


def relation_sql(nodes: str, tag: str, alpha: float = 3.0, minimum: bool = False) -> str:
    """CTE rel{tag} (r, r2, sub, sup, cov, cov2, s_r): forward relations of a and their mirrored inverses."""
    degree = lambda k: f"CASE WHEN count(*) = any_value(n) THEN min(m) ELSE 0 END" if minimum else f"round(least(1.0, {alpha} * round(sum(m) / any_value(n), 9)), 9)"
    flip = lambda c: f"CASE WHEN {c} LIKE '%~' THEN left({c}, length({c}) - 1) ELSE {c} || '~' END"
    return f"""wit{tag} AS MATERIALIZED (SELECT a.r, a.h, a.t, b.r2, max(least(x.s, y.s)) AS m FROM a JOIN {nodes} x ON x.h = a.h JOIN {nodes} y ON y.h = a.t JOIN b ON b.h2 = x.h2 AND b.t2 = y.h2 WHERE a.r NOT LIKE '%~' GROUP BY ALL),
tiw{tag} AS MATERIALIZED (SELECT b.r2, b.h2, b.t2, a.r, max(least(x.s, y.s)) AS m FROM b JOIN {nodes} x ON x.h2 = b.h2 JOIN {nodes} y ON y.h2 = b.t2 JOIN a ON a.h = x.h AND a.t = y.h WHERE a.r NOT LIKE '%~' GROUP BY ALL),
sub{tag} AS (SELECT r, r2, {degree(1)} AS sub, round(sum(m) / any_value(n), 9) AS cov FROM wit{tag} JOIN (SELECT r, count(*) AS n FROM a GROUP BY r) USING (r) GROUP BY r, r2),
sup{tag} AS (SELECT r, r2, {degree(2)} AS sup, round(sum(m) / any_value(n), 9) AS cov2 FROM tiw{tag} JOIN (SELECT r2, count(*) AS n FROM b GROUP BY r2) USING (r2) GROUP BY r, r2),
fwd{tag} AS (SELECT r, r2, coalesce(sub, 0) AS sub, coalesce(sup, 0) AS sup, coalesce(cov, 0) AS cov, coalesce(cov2, 0) AS cov2, greatest(coalesce(sub, 0), coalesce(sup, 0)) AS s_r FROM sub{tag} FULL JOIN sup{tag} USING (r, r2)),
rel{tag} AS MATERIALIZED (SELECT * FROM fwd{tag} UNION ALL SELECT {flip('r')}, {flip('r2')}, sub, sup, cov, cov2, s_r FROM fwd{tag})"""


def two_rounds(name: str = "tiny", longest: int = 2, minimum: bool = False, seeds: str | None = None) -> str:
    """CTEs of two full rounds: mm1, rel1, es2, scores2 and mm2. seeds: SQL of (t, t2)."""

    def pinned(scores: str, out: str) -> str:
        if seeds is None:
            return f"{out} AS MATERIALIZED (SELECT t, t2, score FROM {scores})"
        return f"{out} AS MATERIALIZED (SELECT t, t2, score FROM {scores} WHERE t NOT IN (SELECT t FROM seeds) AND t2 NOT IN (SELECT t2 FROM seeds) UNION ALL SELECT t, t2, 1.0 FROM seeds)"

    start = "lm" if seeds is None else "(SELECT h, h2, s FROM lm UNION ALL SELECT t, t2, 1.0 FROM seeds)"
    known = "SELECT t, t2, score FROM es1" if seeds is None else "SELECT coalesce(s.t, e.t) AS t, coalesce(s.t2, e.t2) AS t2, greatest(coalesce(e.score, 0), CASE WHEN s.t IS NULL THEN 0 ELSE 1 END) AS score FROM es1 e FULL JOIN seeds s ON s.t = e.t AND s.t2 = e.t2"
    return f"""{closed_sql(name)}, {pair_tables('a', 'a')}, {pair_tables('(SELECT r2 AS r, h2 AS h, t2 AS t FROM b)', 'b')}, {literal_matches()}{f", seeds AS MATERIALIZED ({seeds})" if seeds else ""},
{cp_sql(start, None, '1')}, {candidates_sql('1')}, {entity_sql('1', longest, minimum)}, raw1 AS ({known}), {pinned('raw1', 'scores1')}, {mutual_sql('scores1', 'mm1')},
nodes1 AS MATERIALIZED (SELECT h, h2, s FROM lm UNION ALL SELECT t, t2, score FROM mm1 WHERE score > 0), {relation_sql('nodes1', '1', minimum=minimum)},
{cp_sql('nodes1', 'rel1', '2')}, {candidates_sql('2')}, {entity_sql('2', longest, minimum)},
raw2 AS (SELECT coalesce(e.t, m.t) AS t, coalesce(e.t2, m.t2) AS t2, greatest(coalesce(e.score, 0), coalesce(m.score, 0)) AS score FROM es2 e FULL JOIN mm1 m ON m.t = e.t AND m.t2 = e.t2),
{pinned('raw2', 'scores2')}, {mutual_sql('scores2', 'mm2')}"""


def probable_sql(rounds: int, name: str = "tiny", seeds: str | None = None, theta: float = 0.1) -> str:
    """CTEs of the probabilistic aligner up to pe{rounds} (t, t2, score), literals by identity; rounds unrolled."""
    none = "CASE WHEN max({0}) >= 1 THEN 1.0 ELSE 1 - exp(sum(CASE WHEN {0} < 1 THEN ln(1 - {0}) END)) END"
    out = f"""{closed_sql(name)}, {pair_tables('a', 'a')}, {pair_tables('(SELECT r2 AS r, h2 AS h, t2 AS t FROM b)', 'b')}, {NUMBERS},
lm AS MATERIALIZED (SELECT n AS h, n2 AS h2, 1.0::DOUBLE AS s FROM nums UNION ALL SELECT DISTINCT fa.t, fb.t, 1.0 FROM fa JOIN fb ON fa.t = fb.t AND fa.kind = fb.kind AND fa.kind IN ('string', 'date'))"""
    if seeds:
        out += f", seeds AS MATERIALIZED ({seeds})"
    for k in range(1, rounds + 1):
        heads = "lm" if k == 1 else f"pn{k - 1}"
        sims = f"{theta}::DOUBLE AS s1, {theta}::DOUBLE AS s2" if k == 1 else "i.sub AS s1, i.sup AS s2"
        join = "" if k == 1 else f"JOIN ps{k - 1} i ON i.r = a.r AND i.r2 = b.r2 AND greatest(i.sub, i.sup) > 0"
        free = "" if not seeds else " WHERE t NOT IN (SELECT t FROM seeds) AND t2 NOT IN (SELECT t2 FROM seeds) UNION ALL SELECT t, t2, 1.0 FROM seeds"
        out += f""",
pc{k} AS MATERIALIZED (SELECT a.t, b.t2, a.r, b.r2, m.s AS s_h, {sims} FROM {heads} m JOIN a ON a.h = m.h JOIN b ON b.h2 = m.h2 {join} WHERE m.s > 0 AND NOT {LIT.format('a.t')} AND NOT {LIT.format('b.t2')}),
pr{k} AS (SELECT t, t2, 1 - (1 - s2 * ar.f * s_h) * (1 - s1 * br.f * s_h) AS p FROM pc{k} c JOIN ar ON ar.r = c.r JOIN br ON br.r = c.r2),
pw{k} AS MATERIALIZED (SELECT t, t2, round({none.format('p')}, 9) AS score FROM pr{k} GROUP BY t, t2),
px{k} AS MATERIALIZED (SELECT t, t2, score FROM pw{k}{free}),
pe{k} AS MATERIALIZED (SELECT t, t2, score FROM px{k} QUALIFY row_number() OVER (PARTITION BY t ORDER BY score DESC, t2) = 1 AND row_number() OVER (PARTITION BY t2 ORDER BY score DESC, t) = 1)"""
        if k < rounds:
            out += f""",
pn{k} AS MATERIALIZED (SELECT h, h2, s FROM lm UNION ALL SELECT t, t2, score FROM pe{k}),
pq{k} AS MATERIALIZED (SELECT a.r, a.h, a.t, x.h2, y.h2 AS t2, x.s * y.s AS p FROM a JOIN pn{k} x ON x.h = a.h JOIN pn{k} y ON y.h = a.t),
pb{k} AS (SELECT r, sum(p) AS total FROM (SELECT r, h, t, {none.format('p')} AS p FROM pq{k} GROUP BY ALL) GROUP BY r),
pd{k} AS (SELECT r, r2, sum(p) AS s FROM (SELECT q.r, q.h, q.t, b.r2, {none.format('q.p')} AS p FROM pq{k} q JOIN b ON b.h2 = q.h2 AND b.t2 = q.t2 GROUP BY ALL) GROUP BY r, r2),
pv{k} AS MATERIALIZED (SELECT b.r2, b.h2, b.t2, x.h, y.h AS t, x.s * y.s AS p FROM b JOIN pn{k} x ON x.h2 = b.h2 JOIN pn{k} y ON y.h2 = b.t2),
pf{k} AS (SELECT r2, sum(p) AS total FROM (SELECT r2, h2, t2, {none.format('p')} AS p FROM pv{k} GROUP BY ALL) GROUP BY r2),
pg{k} AS (SELECT r, r2, sum(p) AS s FROM (SELECT q.r2, q.h2, q.t2, a.r, {none.format('q.p')} AS p FROM pv{k} q JOIN a ON a.h = q.h AND a.t = q.t GROUP BY ALL) GROUP BY r, r2),
ps{k} AS MATERIALIZED (SELECT r, r2, coalesce(sub, 0) AS sub, coalesce(sup, 0) AS sup FROM (SELECT r, r2, s / total AS sub FROM pd{k} JOIN pb{k} USING (r)) FULL JOIN (SELECT r, r2, s / total AS sup FROM pg{k} JOIN pf{k} USING (r2)) USING (r, r2))"""
    return out
