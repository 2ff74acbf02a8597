"""DuckDB twins of the study: entries, hand-written narratives, bootstrapping, the technique grid, validation and reports.

Long form throughout: a row per feature or token where the engine keeps arrays in the row, and the
authored slot texts where the engine reads its slots from the finished narratives.
"""

from __future__ import annotations

from narrative_engine.fixtures import CLAUSES, STYLE_PARTS, ZERO_SHOT
from narrative_engine.operators.grading import STYLE_STEP
from narrative_engine.plans.experiments import BOOT, GAP_DRAWS, ROUNDS
from narrative_engine.plans.twins import WORDS, claims_ctes, concise, filled, quoted, told, top_ctes
from narrative_engine.settings import BASE_PROMPTS, CATEGORIES, GATE, SET_ASIDE, STYLES, TECHNIQUES, WEIGHTS
from narrative_engine.sources.tables import NUMERIC

DOMAINS = sorted({d for d, _, _ in STYLES.values()})


def values(name: str, columns: str, rows: list[tuple]) -> str:
    text = ", ".join("(" + ", ".join(quoted(v) if isinstance(v, str) else str(v).lower() if isinstance(v, bool) else str(v) for v in r) + ")" for r in rows)
    return f"{name}({columns}) AS (VALUES {text})"


def entries_ctes() -> str:
    tops = ",\n".join(top_ctes(d, 3, f"{d}_") for d in DOMAINS)
    union = " UNION ALL ".join(f"SELECT '{d}' AS domain, row_id, place, feature, value, value_num, contribution FROM {d}_top" for d in DOMAINS)
    styles = values("styles", "style, domain, quota", [(s, d, n) for s, (d, n, _) in STYLES.items()])
    return f"""{tops},
alltop AS MATERIALIZED ({union}),
{styles},
e AS MATERIALIZED (SELECT style, domain, row_id, place FROM (
  SELECT style, domain, row_id, quota, row_number() OVER (PARTITION BY style ORDER BY md5(style || '|' || row_id), row_id) AS place FROM styles JOIN (SELECT DISTINCT domain, row_id FROM alltop) USING (domain)) WHERE place <= quota),
ex AS MATERIALIZED (SELECT e.style, e.row_id, e.place AS eplace, t.place, feature, value, value_num, contribution FROM e JOIN alltop t ON t.domain = e.domain AND t.row_id = e.row_id)"""


def hand_ctes() -> str:
    parts = values("sp", "style, lead, up, down, joiner, tail", [(s, *p) for s, p in STYLE_PARTS.items()])
    clauses = values("cl", "style, ex, slots, omits", [(s, k + 1, c, flaw == "omits") for s, own in CLAUSES.items() for k, (c, flaw) in enumerate(own)])
    return f"""{parts},
{clauses},
hand AS MATERIALIZED (
  SELECT style, row_id, eplace, sp.lead || replace(string_agg({filled('cl.slots', 'sp.up', 'sp.down')}, chr(1) ORDER BY place), chr(1), sp.joiner) || sp.tail AS text
  FROM ex JOIN cl USING (style) JOIN sp USING (style) WHERE eplace <= 5 AND cl.ex = eplace AND place <= 3 - omits::INT GROUP BY style, row_id, eplace, sp.lead, sp.joiner, sp.tail)"""


def masked(text: str) -> str:
    """Features and values of ``fs`` and ``vs`` replaced, then numbers."""
    for k in (1, 2, 3):
        text = f"replace(replace({text}, vs[{k}], 'y'), fs[{k}], 'x')"
    return f"regexp_replace({text}, '[0-9]+(?:\\.[0-9]+)?', '0', 'g')"


def vector(text: str) -> str:
    n = f"greatest({WORDS.format(text)}, 1)"
    times = lambda s: f"CAST((length({text}) - length(replace({text}, '{s}', ''))) / {len(s)} AS INT)"
    rate = lambda s: f"CAST(floor({times(s)} * 100 / {n}) AS INT)"
    clauses = f"len(string_split_regex({text}, '[.;!?](?:\\s|$)|, while |, but ')) - 1"
    cells = [rate(","), rate("("), rate(";"), rate("about"), f"{rate('We ')} + {rate('our ')}", rate("!"), rate("0"), rate("which"), rate("feature"), f"CAST(floor({n} / greatest({clauses}, 1)) AS INT)", f"CAST(floor((length({text}) - {n}) * 2 / {n}) AS INT)"]
    return f"[{', '.join(cells)}]"


def vectors_cte(name: str, source: str, key: str, join: str, mask: bool = True) -> str:
    """``name``: ``source`` rows (style, ..., text) with v; ``join`` ties them to ``ex``'s row."""
    text = masked("text") if mask else "text"
    return f"""{name} AS MATERIALIZED (SELECT {key}, text, {vector('mt')} AS v FROM (SELECT s.*, {text} AS mt FROM {source} s JOIN fv ON {join}) s)"""


FEATURE_LISTS = "fv AS MATERIALIZED (SELECT style, row_id, list(feature ORDER BY place) AS fs, list(value ORDER BY place) AS vs FROM ex GROUP BY style, row_id)"


def centre(source: str, by: str = "style") -> str:
    sums = ", ".join(f"CAST(floor(CAST(sum(v[{i}]) AS DOUBLE) / count(*)) AS INT)" for i in range(1, 12))
    return f"SELECT {by}, [{sums}] AS centre FROM {source} GROUP BY {by}"


DISTANCE = "list_sum(list_transform(range(1, 12), lambda i: abs(v[i] - centre[i])))"
FLUENCY = f"greatest(0, 4 - CAST(floor({DISTANCE} / {STYLE_STEP}) AS INT))"


def refs_ctes() -> str:
    return f"""{FEATURE_LISTS},
{vectors_cte('hv', 'hand', 's.style, s.row_id, eplace', 'fv.style = s.style AND fv.row_id = s.row_id')},
refs AS MATERIALIZED (SELECT * FROM ({centre('hv')}) JOIN (SELECT style, max({WORDS.format('text')} / 3.0::DOUBLE) * 0.9::DOUBLE AS longest FROM hand GROUP BY style) USING (style))"""


def graded_cte(name: str, source: str, p: str, keys: str) -> str:
    """Grades of ``source`` (k, style, row_id, keys, text), whose claims have prefix ``p``."""
    words = WORDS.format("text")
    return f"""{vectors_cte(p + 'sv', source, 's.k', 'fv.style = s.style AND fv.row_id = s.row_id')},
{name} AS MATERIALIZED (
  SELECT *, {WEIGHTS['a']} * a + {WEIGHTS['f']} * f + {WEIGHTS['c']} * c + {WEIGHTS['s']} * s AS total FROM (
    SELECT s.k, s.style, s.row_id, {keys}, s.text, v.a::INT AS a, v.c::INT AS c, {FLUENCY.replace('v[i]', 'sv.v[i]')}::INT AS f, {concise(words.replace('text', 's.text'), '3 * longest')} AS s
    FROM {source} s JOIN {p}v v ON v.k = s.k JOIN {p}sv sv ON sv.k = s.k JOIN refs ON refs.style = s.style))"""


def boot_ctes() -> str:
    gate = " AND ".join(f"{k} >= {v}" for k, v in GATE.items())
    return f"""rounds AS (SELECT unnest(range(1, {ROUNDS + 1})) AS r),
bd AS MATERIALIZED (SELECT * FROM (
  SELECT e.style, e.row_id, e.place, r, cl.ex, cl.omits, row_number() OVER (PARTITION BY e.style, e.row_id, r ORDER BY md5(concat_ws('|', e.style, e.row_id, 'boot', r, cl.ex))) AS o, 1 + (r - 1) % 3 AS n_ex
  FROM e CROSS JOIN rounds JOIN cl ON cl.style = e.style WHERE e.place > 5 AND e.place <= {SET_ASIDE}) WHERE o <= n_ex),
bo AS (SELECT style, row_id, place, r, n_ex, omits FROM bd WHERE o = 1),
bc AS MATERIALIZED (
  SELECT ex.style || '|' || ex.row_id || '|' || bo.r AS k, ex.style, ex.row_id, bo.place AS eplace, bo.r, bo.omits, ex.place, bd.ex, {filled('cl.slots', 'sp.up', 'sp.down')} AS part
  FROM bo JOIN ex ON ex.style = bo.style AND ex.row_id = bo.row_id JOIN bd ON bd.style = bo.style AND bd.row_id = bo.row_id AND bd.r = bo.r AND bd.o = 1 + (ex.place - 1) % bo.n_ex
  JOIN cl ON cl.style = bd.style AND cl.ex = bd.ex JOIN sp ON sp.style = bo.style WHERE ex.place <= 3 - bo.omits::INT),
bn AS MATERIALIZED (SELECT k, style, row_id, eplace, r, omits, sp.lead || replace(string_agg(part, chr(1) ORDER BY place), chr(1), sp.joiner) || sp.tail AS text, list(ex ORDER BY place) AS used FROM bc JOIN sp USING (style) GROUP BY k, style, row_id, eplace, r, omits, sp.lead, sp.joiner, sp.tail),
bx AS (SELECT k, place, feature, value, value_num, contribution FROM bn JOIN ex USING (style, row_id)),
{claims_ctes('bn', 'bx', 'b_')},
{graded_cte('bg', 'bn', 'b_', 's.eplace, s.r, s.omits, s.used')},
acc AS MATERIALIZED (SELECT *, md5(concat_ws('|', 'boot', style, r, eplace)) AS key FROM bg WHERE {gate}),
pool AS MATERIALIZED (SELECT * FROM (
  SELECT *, row_number() OVER (PARTITION BY style ORDER BY r, key) AS b FROM (SELECT *, row_number() OVER (PARTITION BY style, text ORDER BY r, key) AS same FROM acc) WHERE same = 1) WHERE b <= {BOOT})"""


def grid_ctes(where: str = f"e.place > {SET_ASIDE}") -> str:
    techniques = values("tq", "technique, base, h, b", list(TECHNIQUES))
    zero = values("zp", "base, lead, slots, up, down, joiner, tail", [(b, *z) for b, z in ZERO_SHOT.items()])
    return f"""{techniques},
{zero},
dh AS (SELECT e.style, e.row_id, cl.ex, cl.omits, [cl.ex] AS used, md5(e.style || '|' || e.row_id || '|h' || cl.ex) AS key, row_number() OVER (PARTITION BY e.style, e.row_id ORDER BY md5(e.style || '|' || e.row_id || '|h' || cl.ex)) AS o FROM e JOIN cl USING (style) WHERE {where}),
db AS (SELECT e.style, e.row_id, p.b AS ex, p.omits, p.used, md5(e.style || '|' || e.row_id || '|b' || p.b) AS key, row_number() OVER (PARTITION BY e.style, e.row_id ORDER BY md5(e.style || '|' || e.row_id || '|b' || p.b)) AS o FROM e JOIN pool p USING (style) WHERE {where}),
dx AS MATERIALIZED (
  SELECT *, row_number() OVER (PARTITION BY style, row_id, technique ORDER BY key) - 1 AS nth, count(*) OVER (PARTITION BY style, row_id, technique) AS n_ex FROM (
    SELECT dh.*, technique FROM dh CROSS JOIN tq WHERE o <= tq.h UNION ALL SELECT db.*, technique FROM db CROSS JOIN tq WHERE o <= tq.b)),
gp AS MATERIALIZED (
  SELECT ex.style, ex.row_id, t.technique, ex.place, {filled('cl.slots', 'sp.up', 'sp.down')} AS part
  FROM dx f JOIN tq t ON t.technique = f.technique JOIN ex ON ex.style = f.style AND ex.row_id = f.row_id JOIN dx d ON d.style = f.style AND d.row_id = f.row_id AND d.technique = f.technique AND d.nth = (ex.place - 1) % f.n_ex
  JOIN cl ON cl.style = d.style AND cl.ex = d.used[least(ex.place, len(d.used))] JOIN sp ON sp.style = f.style WHERE f.nth = 0 AND ex.place <= 3 - f.omits::INT),
gz AS (SELECT ex.style, ex.row_id, t.technique, t.base, ex.place, {filled('z.slots', 'z.up', 'z.down')} AS part FROM ex JOIN e ON e.style = ex.style AND e.row_id = ex.row_id JOIN tq t ON t.h + t.b = 0 JOIN zp z ON z.base = t.base WHERE {where}),
gt AS MATERIALIZED (
  SELECT style || '|' || row_id || '|' || technique AS k, * FROM (
    SELECT style, row_id, technique, sp.lead || replace(string_agg(part, chr(1) ORDER BY place), chr(1), sp.joiner) || sp.tail AS text FROM gp JOIN sp USING (style) GROUP BY style, row_id, technique, sp.lead, sp.joiner, sp.tail
    UNION ALL SELECT style, row_id, technique, z.lead || replace(string_agg(part, chr(1) ORDER BY place), chr(1), z.joiner) || z.tail FROM gz JOIN zp z USING (base) GROUP BY style, row_id, technique, z.lead, z.joiner, z.tail))"""


GRADED_GRID = f"""gx AS (SELECT k, place, feature, value, value_num, contribution FROM gt JOIN ex USING (style, row_id)),
{claims_ctes('gt', 'gx', 'g_')},
{graded_cte('gg', 'gt', 'g_', 's.technique')}"""

ENTRIES = f"WITH {entries_ctes()}"
HAND = f"{ENTRIES},\n{hand_ctes()}"
REFS = f"{HAND},\n{refs_ctes()}"
POOL = f"{REFS},\n{boot_ctes()}"
TEXTS = f"{POOL},\n{grid_ctes()}"
GRID = f"{TEXTS},\n{GRADED_GRID}"

UNIT = {"accuracy": ("a", WEIGHTS["a"]), "completeness": ("c", WEIGHTS["c"]), "fluency": ("f", WEIGHTS["f"]), "conciseness": ("s", WEIGHTS["s"]), "total": ("total", 1.0)}


def units(c: str, w: float) -> str:
    return f"CAST(floor({c} * {w}::DOUBLE * 10000 + 0.5) AS BIGINT)"


MEANS = ", ".join(f"floor(sum({units(c, w)}) / count(*) + 0.5) / 10000 AS {n}" for n, (c, w) in UNIT.items())
SCORES = f"SELECT technique, base, h, b, count(*) AS n, {MEANS} FROM gg JOIN tq USING (technique) GROUP BY technique, base, h, b"
LONG = " UNION ALL ".join(f"SELECT technique, h, b, '{n}' AS metric, {n} AS score FROM scores" for n in UNIT)
SCORED = f"{GRID},\nscores AS MATERIALIZED ({SCORES}),\nlong AS ({LONG})"
MEAN_OF_METRICS = {"equal": (1, 1, 1, 1), "correctness": (3, 3, 1, 1), "style": (1, 1, 3, 3), "accuracy": (5, 1, 1, 1), "short": (1, 1, 1, 5)}


def deviation(n: str, s: str, q: str, sample: bool = False) -> str:
    down = f"({n}) * (({n}) - 1)" if sample else f"({n}) * ({n})"
    return f"CASE WHEN {down} > 0 THEN floor(sqrt(CAST(greatest(({n}) * ({q}) - ({s}) * ({s}), 0) AS DOUBLE) / CAST({down} AS DOUBLE)) / 10000.0::DOUBLE * 10000.0::DOUBLE + 0.5) / 10000.0::DOUBLE END"


def spread(source: str, by: str, across: str) -> str:
    """CTEs ``inn`` and ``outr``: spreads over narratives, and over the means of groups."""
    over = ", ".join(f"{deviation('count(*)::HUGEINT', f'sum({units(c, w)}::HUGEINT)', f'sum({units(c, w)}::HUGEINT * {units(c, w)})')} AS {n}_over_narratives" for n, (c, w) in UNIT.items())
    groups = ", ".join(f"CAST(floor(sum({units(c, w)}) / count(*) + 0.5) AS BIGINT) AS {n}" for n, (c, w) in UNIT.items())
    far = ", ".join(f"{deviation('count(*)::HUGEINT', f'sum({n}::HUGEINT)', f'sum({n}::HUGEINT * {n})', k)} AS {n}_{name}" for n in UNIT for k, name in ((False, "across"), (True, "across_sample")))
    return f"inn AS (SELECT {by}, count(*) AS n, {over} FROM {source} GROUP BY {by}),\ngrp AS (SELECT {by}, {across}, {groups} FROM {source} GROUP BY {by}, {across}),\noutr AS (SELECT {by}, {far} FROM grp GROUP BY {by})"


def uniform(key: str) -> str:
    return f"CAST(('0x' || substr(md5({key}), 1, 6)) AS INT) / 16777216.0::DOUBLE"


def pearson(x: str, y: str) -> str:
    n, vx, vy = "count(*)", f"(count(*) * sum({x} * {x}) - sum({x}) * sum({x}))::DOUBLE", f"(count(*) * sum({y} * {y}) - sum({y}) * sum({y}))::DOUBLE"
    return f"CASE WHEN {vx} > 0 AND {vy} > 0 THEN ({n} * sum({x} * {y}) - sum({x}) * sum({y}))::DOUBLE / sqrt({vx}) / sqrt({vy}) END"


def half_up(x: str, digits: int) -> str:
    k = f"{float(10**digits)}::DOUBLE"
    return f"floor(({x}) * {k} + 0.5::DOUBLE) / {k}"


# --- validation


def pairs_ctes(metric: str) -> str:
    cases, at = [], 0
    for m, category, grade, n in CATEGORIES:
        if m == metric:
            cases.append((category, grade, at, at + n))
            at += n
    key = f"md5('{metric}|' || style || '|' || row_id)"
    size = "abs(contribution)"
    fill = lambda slot: filled(f"'{slot}'", "''", "''")
    first, odd = "place = 1", "pair_id % 2 = 1"
    amount = f"CASE WHEN category = 'approximate values' THEN {fill('{r}')} WHEN category = 'value error' AND {first} THEN {fill('{k}')} ELSE printf('%.2f', {size}) END"
    with_value = f"NOT (category = 'value or direction missing' AND {first} AND {odd}) AND NOT (category = 'some values' AND NOT ({first}))"
    with_way = f"NOT (category = 'value or direction missing' AND {first} AND NOT ({odd}))"
    with_amount = f"category IN ('all values', 'approximate values', 'value error', 'everything') OR (category = 'some values' AND {first})"
    way = f"CASE WHEN (contribution < 0) <> (category = 'direction error' AND {first}) THEN 'lowers the output' ELSE 'raises the output' END"
    sentence = f"'The ' || feature || CASE WHEN {with_value} THEN ' is ' || value || ' and' ELSE '' END || CASE WHEN {with_way} THEN ' ' || {way} ELSE ' counts' END || CASE WHEN {with_amount} THEN ' by ' || ({amount}) ELSE '' END || '.'"
    return f"""{values('cases', 'category, human, lo, hi', cases)},
pr AS MATERIALIZED (SELECT style || '|' || row_id AS k, style, row_id, pair_id, category, human FROM (
  SELECT style, row_id, row_number() OVER (ORDER BY {key}, style, row_id) - 1 AS pair_id FROM e) JOIN cases ON pair_id >= lo AND pair_id < hi),
px AS MATERIALIZED (SELECT k, pair_id, category, place, feature, value, value_num, contribution FROM pr JOIN ex USING (style, row_id)),
pt AS MATERIALIZED (SELECT k, string_agg({sentence}, ' ' ORDER BY place) AS text FROM px WHERE category <> 'feature missing' OR place < 3 GROUP BY k),
{claims_ctes('pt', 'px', 'p_')},
pg AS MATERIALIZED (SELECT '{metric}' AS metric, pr.*, {'a' if metric == 'accuracy' else 'c'}::INT AS grader FROM pr JOIN p_v USING (k))"""


def pairs(metric: str) -> str:
    return f"{ENTRIES},\n{pairs_ctes(metric)}"


def validation(metric: str) -> dict[str, str]:
    top = 2 if metric == "accuracy" else 3
    counts = f"{pairs(metric)},\nct AS (SELECT metric, human, grader, count(*) AS n FROM pg GROUP BY ALL)"
    cells = ", ".join(f"count(*) FILTER (WHERE grader = {k}) AS grader_{k}" for k in range(top))
    chance = "x AS (SELECT h.metric, sum(a * b)::DOUBLE AS x FROM (SELECT metric, human AS c, sum(n) AS a FROM ct GROUP BY ALL) h JOIN (SELECT metric, grader AS c, sum(n) AS b FROM ct GROUP BY ALL) g USING (metric, c) GROUP BY h.metric)"
    return {
        f"validate_{metric}": f"{pairs(metric)}\nSELECT category, count(*) AS n, count(*) FILTER (WHERE human = grader) AS agreed FROM pg GROUP BY category",
        f"confusion_{metric}": f"{pairs(metric)}\nSELECT human, {cells} FROM pg GROUP BY human",
        f"agreement_{metric}": f"{counts},\nt AS (SELECT metric, sum(n)::DOUBLE AS al, sum(CASE WHEN human = grader THEN n ELSE 0 END)::DOUBLE AS same FROM ct GROUP BY metric),\n{chance}\nSELECT metric, al::BIGINT AS n, floor(same / al * 10000 + 0.5) / 10000 AS agreement, floor((same / al - x / (al * al)) / (1 - x / (al * al)) * 10000 + 0.5) / 10000 AS kappa FROM t JOIN x USING (metric)",
        f"classes_{metric}": f"""{pairs(metric)},
m AS (SELECT metric, human AS class, count(*) AS meant, count(*) FILTER (WHERE human = grader) AS hit FROM pg GROUP BY ALL), s AS (SELECT metric, grader AS class, count(*) AS said FROM pg GROUP BY ALL)
SELECT metric, class, CASE WHEN coalesce(said, 0) > 0 THEN floor(hit::DOUBLE / said * 10000 + 0.5) / 10000 END AS precision, floor(hit::DOUBLE / meant * 10000 + 0.5) / 10000 AS recall FROM m LEFT JOIN s USING (metric, class)""",
    }


def revised(metric: str, grades: list[tuple[str, str]], more: str = "") -> str:
    """``grades``: SQL of each policy's grade, from aggregates by pair ``k``."""
    rows = " UNION ALL ".join(f"SELECT {i} AS place, {quoted(name)} AS policy, count(*) AS n, count(*) FILTER (WHERE {sql} = human) AS agreed FROM pol" for i, (name, sql) in enumerate(grades))
    return f"""{pairs(metric)}{more},
pol AS MATERIALIZED (SELECT pr.k, human, any_value(v.invented) AS invented, count(*) AS m, count(*) FILTER (WHERE wrong) AS n_wrong, count(*) FILTER (WHERE way < 0) AS n_way, count(*) FILTER (WHERE wrong OR way < 0) AS n_bad,
  count(*) FILTER (WHERE NOT mentioned OR NOT has_value) AS n_missing, count(*) FILTER (WHERE NOT mentioned) AS n_unnamed, count(*) FILTER (WHERE has_value AND way <> 0) AS n_full, count(*) FILTER (WHERE mentioned AND NOT (has_value AND way <> 0)) AS n_part,
  count(*) FILTER (WHERE has_value AND way <> 0 AND contribution_told) AS n_all{', any_value(t0.a0) AS a0' if more else ''}
  FROM pr JOIN p_g g USING (k) JOIN p_v v USING (k){' JOIN t0 USING (k)' if more else ''} GROUP BY pr.k, human),
r AS ({rows}),
s AS (SELECT *, agreed >= 0.95 * n AS reached FROM r)
SELECT *, row_number() OVER (ORDER BY reached DESC, CASE WHEN reached THEN 0 ELSE -agreed END, place) = 1 AS chosen FROM s"""


ACCURACY_GRADES = [
    ("plain question", "CASE WHEN n_wrong > 0 OR n_missing > 0 THEN 0 ELSE 1 END"), ("yes or no", "CASE WHEN 2 * n_bad > m THEN 0 ELSE 1 END"),
    ("two points", "CASE WHEN n_wrong > 0 OR invented OR n_missing > 0 THEN 0 ELSE 1 END"), ("omission is fine", "CASE WHEN n_wrong > 0 OR invented THEN 0 ELSE 1 END"),
    ("directions count", "CASE WHEN n_bad > 0 OR invented THEN 0 ELSE 1 END"), ("step by step", "CASE WHEN n_bad > 0 OR invented THEN 0 ELSE 1 END"), ("three points", "CASE WHEN n_bad > 0 OR invented THEN 0 ELSE 1 END"),
    ("no tolerance", "a0"),
]
COMPLETENESS_GRADES = [
    ("plain question", "CASE WHEN n_unnamed = m THEN 0 WHEN n_part = 0 THEN 2 ELSE 1 END"), ("checklist", "CASE WHEN n_unnamed > 0 THEN 0 WHEN n_full = m THEN 2 ELSE 1 END"),
    ("contributions required", "CASE WHEN n_unnamed > 0 THEN 0 WHEN n_all = m THEN 2 ELSE 1 END"),
]


def correlation() -> str:
    err = lambda m, top: f"CAST(floor(list_sum(list_transform(range(1, 6), lambda i: CASE WHEN {uniform(f'concat_ws(chr(124), {quoted(m)}, style, row_id, i)')} < 0.1 THEN {top} - grader ELSE grader END)) / 5.0::DOUBLE + 0.5) AS INT)"
    one = lambda m, top: f"({pairs(m)} SELECT metric, human::BIGINT AS x, ({err(m, top)})::BIGINT AS y FROM pg)"
    rank = lambda c: f"2 * rank() OVER (PARTITION BY metric ORDER BY {c}) + count(*) OVER (PARTITION BY metric, {c})"
    return f"""WITH pa AS ({one('accuracy', 1)} UNION ALL {one('completeness', 2)}),
r AS (SELECT metric, x, y, {rank('x')} AS rx, {rank('y')} AS ry FROM pa)
SELECT metric, count(*) AS n, {half_up(pearson('x', 'y'), 4)} AS pearson, {half_up(pearson('rx', 'ry'), 4)} AS spearman FROM r GROUP BY metric"""


# --- style gaps


def gaps(mask: bool = True) -> str:
    sizes = ", ".join(f"({n}, {d})" for n in (1, 2, 3, 4) for d in range(1, GAP_DRAWS + 1))
    return f"""{HAND},
{FEATURE_LISTS},
{vectors_cte('hv', 'hand', 's.style, s.row_id, eplace', 'fv.style = s.style AND fv.row_id = s.row_id', mask)},
cs(n, draw) AS (VALUES {sizes}),
rw AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY n, draw, style ORDER BY md5(concat_ws('|', n, draw, style, eplace)), eplace) AS place FROM hv CROSS JOIN cs),
ce AS MATERIALIZED ({centre('(SELECT * FROM rw WHERE place <= n)', 'n, draw, style')}),
ju AS (SELECT rw.n, rw.draw, rw.style, ce.style AS against, {FLUENCY} AS f FROM rw JOIN ce ON ce.n = rw.n AND ce.draw = rw.draw WHERE place > rw.n),
ow AS (SELECT n, draw, style, sum(f) AS own, count(*) AS m FROM ju WHERE style = against GROUP BY ALL),
ot AS (SELECT n, draw, style, max(o) AS other FROM (SELECT n, draw, style, against, sum(f) AS o FROM ju WHERE style <> against GROUP BY ALL) GROUP BY ALL),
gp AS (SELECT n, CAST(floor(own * 10000 / m + 0.5) AS BIGINT) AS own, CAST(floor(other * 10000 / m + 0.5) AS BIGINT) AS other FROM ow JOIN ot USING (n, draw, style)),
ga AS (SELECT n, floor(sum(own) / count(*) + 0.5) / 10000 AS own, floor(sum(other) / count(*) + 0.5) / 10000 AS other, floor(sum(own - other) / count(*) + 0.5) / 10000 AS gap, min(own - other) / 10000 AS worst FROM gp GROUP BY n)"""


def fluency_forms() -> str:
    out = []
    for name, mask, pooled, k in (("masked", True, False, 5), ("unmasked", False, False, 5), ("pooled", True, True, 5), ("one exemplar", True, False, 1)):
        v = "hm" if mask else "hu"
        source = f"(SELECT * FROM {v} WHERE eplace <= {k})"
        ce = f"(SELECT style, centre FROM (SELECT DISTINCT style FROM {v}) CROSS JOIN ({centre(source, chr(39) + 'x' + chr(39))}))" if pooled else f"({centre(source)})"
        out.append(f"SELECT '{name}' AS form, style, count(*) AS n, sum({FLUENCY})::BIGINT AS points FROM {v} JOIN {ce} c USING (style) GROUP BY style")
    tie = "fv.style = s.style AND fv.row_id = s.row_id"
    return f"{HAND},\n{FEATURE_LISTS},\n{vectors_cte('hm', 'hand', 's.style, s.row_id, eplace', tie)},\n{vectors_cte('hu', 'hand', 's.style, s.row_id, eplace', tie, False)}\n" + " UNION ALL ".join(out)


# --- other workloads


def comparatives() -> str:
    larger = {"with statistics": "value_num >= usual", "without": "contribution >= 0"}
    clause = lambda c: f"'A ' || CASE WHEN {c} THEN 'larger ' ELSE 'smaller ' END || feature || ' than most' || CASE WHEN contribution < 0 THEN ' lowers' ELSE ' raises' END || ' the output.'"
    means = " UNION ALL ".join(f"SELECT '{c.replace('_', ' ')}' AS feature, sum({c})::DOUBLE / count(*)::DOUBLE AS usual FROM f" for c in NUMERIC["junk"])
    texts = " UNION ALL ".join(f"SELECT row_id || '|{w}' AS k, '{w}' AS writer, string_agg({clause(c)}, ' ' ORDER BY place) AS text FROM u GROUP BY row_id" for w, c in larger.items())
    both = " UNION ALL ".join(f"SELECT row_id || '|{w}' AS k, place, feature, value, value_num, contribution, usual FROM u" for w in larger)
    return f"""WITH {top_ctes('junk')},
us AS MATERIALIZED ({means}), u AS MATERIALIZED (SELECT top.*, usual FROM top JOIN us USING (feature)),
n AS MATERIALIZED ({texts}), tx AS (SELECT * EXCLUDE (usual), usual AS mean FROM ({both})),
{claims_ctes('n', 'tx', 'i_', usual='mean')},
{claims_ctes('n', 'tx', 'b_')}
SELECT writer, count(*) AS n, sum(i_v.a)::BIGINT AS accurate_if_informed, sum(b_v.a)::BIGINT AS accurate_if_blind FROM n JOIN i_v USING (k) JOIN b_v USING (k) GROUP BY writer"""


SIGNATURES = "sg AS (SELECT row_id, string_agg(feature || CASE WHEN contribution < 0 THEN '-' ELSE '+' END, '|' ORDER BY place) AS signature FROM top GROUP BY row_id)"


def positive_features() -> str:
    texts = " UNION ALL ".join(f"SELECT row_id || '|{w}' AS k, row_id, '{w}' AS wording, 'Its ' || string_agg(feature || ' (' || value || ')', ' and its ' ORDER BY place) || ' make abuse {w}.' AS text FROM up GROUP BY row_id" for w in ("more likely", "less likely"))
    both = " UNION ALL ".join(f"SELECT row_id || '|{w}' AS k, place, feature, value, value_num, contribution FROM up" for w in ("more likely", "less likely"))
    return f"""WITH {top_ctes('toxic', 2)},
up AS MATERIALIZED (SELECT * FROM top WHERE row_id IN (SELECT row_id FROM top GROUP BY row_id HAVING bool_and(contribution > 0))),
n AS MATERIALIZED ({texts}), tx AS ({both}),
{claims_ctes('n', 'tx')}
SELECT row_id, wording, a::INT AS a FROM n JOIN v USING (k)"""


def direct() -> str:
    """Named features by distance from their mean; the directions guessed are graded against the contributions."""
    z = " UNION ALL ".join(f"SELECT row_id, '{c.replace('_', ' ')}' AS feature, CASE WHEN s > 0 THEN ({c}::DOUBLE - m) / s ELSE 0.0::DOUBLE END AS z FROM f, (SELECT avg({c}::DOUBLE) AS m, stddev_pop({c}::DOUBLE) AS s FROM f)" for c in NUMERIC["basket"])
    return f"""WITH {top_ctes('basket', 12)},
gs AS MATERIALIZED (SELECT row_id, feature, CAST(sign(z) AS INT) AS direction, r FROM (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY -abs(z), feature) AS r FROM ({z})) WHERE r <= 3),
n AS MATERIALIZED (SELECT row_id AS k, string_agg('The ' || feature || CASE WHEN direction < 0 THEN ' lowers' ELSE ' raises' END || ' the estimate.', ' ' ORDER BY r) AS text FROM gs GROUP BY row_id),
tx AS (SELECT row_id AS k, row_number() OVER (PARTITION BY row_id ORDER BY place) AS place, feature, value, value_num, contribution FROM top JOIN gs USING (row_id, feature)),
{claims_ctes('n', 'tx')}
SELECT 3 AS named, count(*) AS n, sum(a)::BIGINT AS accurate FROM v"""


def user_style(shown: str, tail: str) -> str:
    fill = filled("'{f} {v} {d} the odds by {c}'", "'pushes up'", "'pushes down'")
    joiner = "CASE WHEN md5(row_id || '|1') < md5(row_id || '|2') THEN ', ' ELSE '; ' END"
    return f"""WITH {top_ctes('spend')},
n AS MATERIALIZED (SELECT row_id AS k, 'Look at this customer: ' || replace(string_agg({fill}, chr(1) ORDER BY place), chr(1), {joiner}) || '.' AS text FROM top GROUP BY row_id){shown}
{tail}"""


def day_texts() -> str:
    fill = filled("'{f} at {v} {d} the day''s value by {c}'", "'drives up'", "'drives down'")
    seeds = "sd AS (SELECT signature, count(*) AS n, min(row_id) AS row_id FROM sg GROUP BY signature ORDER BY n DESC, signature LIMIT 5)"
    text = f"'Today ' || string_agg({fill}, '; ' ORDER BY place) || '.'"
    words = WORDS.format("text")
    bar = "rpad(feature, 18, ' ') || repeat(CASE WHEN contribution < 0 THEN '-' ELSE '+' END, CASE WHEN most > 0 THEN CAST(floor(abs(contribution) / most * 20 + 0.5) AS INT) ELSE 0 END)"
    return f"""WITH {top_ctes('activity')},
{SIGNATURES}, {seeds},
n AS MATERIALIZED (SELECT row_id AS k, row_id, {text} AS text FROM top GROUP BY row_id),
ex AS (SELECT 'own' AS style, * FROM top), {FEATURE_LISTS},
st AS (SELECT 'own' AS style, n.row_id, n.k, text FROM n), {vectors_cte('sv', 'st', 's.k, s.row_id', 'fv.row_id = s.row_id')},
ce AS ({centre('(SELECT ' + chr(39) + 'own' + chr(39) + ' AS style, sv.* FROM sv JOIN sd USING (row_id))')}), lg AS (SELECT max({words} / 3.0::DOUBLE) * 0.9::DOUBLE AS longest FROM n JOIN sd USING (row_id)),
tx AS (SELECT row_id AS k, * EXCLUDE (row_id) FROM top),
{claims_ctes('n', 'tx')},
gr AS (SELECT n.k, n.text, 6.0 * a + 0.5 * ({FLUENCY.replace('v[i]', 'sv.v[i]')}) + 2.0 * c + 0.5 * ({concise(words.replace('text', 'n.text'), '3 * longest')}) AS total FROM n JOIN v ON v.k = n.k JOIN sv ON sv.k = n.k CROSS JOIN ce CROSS JOIN lg),
br AS (SELECT row_id AS k, string_agg({bar}, chr(10) ORDER BY place) AS bars FROM (SELECT *, max(abs(contribution)) OVER (PARTITION BY row_id) AS most FROM top) GROUP BY row_id)
SELECT k AS row_id, CASE WHEN total >= 12.0 THEN text ELSE bars END AS shown, total < 12.0 AS rejected FROM gr JOIN br USING (k)"""


def extras() -> str:
    n = "count(*)::DOUBLE"
    cards = " UNION ALL ".join(f"SELECT '{c.replace('_', ' ')}' AS feature, sum({c})::DOUBLE / {n} AS m, sqrt(greatest(0.0::DOUBLE, sum(CAST({c} * {c} AS DECIMAL(34,6)))::DOUBLE / {n} - (sum({c})::DOUBLE / {n}) * (sum({c})::DOUBLE / {n}))) AS s FROM f" for c in NUMERIC["junk"])
    band = "CASE WHEN s > 0 THEN CASE WHEN (value_num - m) / s > 0.5 THEN ', larger than usual' WHEN (value_num - m) / s < -0.5 THEN ', smaller than usual' ELSE ', as usual' END ELSE '' END"
    return f"""WITH {top_ctes('junk')}, card AS ({cards})
SELECT row_id, string_agg('(' || feature || ', ' || value || ', ' || printf('%.2f', contribution + 0.0) || ', usually ' || printf('%.2f', floor(m * 100 + 0.5) / 100) || {band} || ')', ', ' ORDER BY place) AS expl_text FROM top JOIN card USING (feature) GROUP BY row_id"""


RULES = """WITH r AS (
  SELECT o_orderkey, 'priority is ' || o_orderpriority AS c1, CASE WHEN starts_with(o_orderpriority, '1') THEN 'ship first' ELSE 'ship in turn' END AS o1, 'status is ' || o_orderstatus AS c2, CASE WHEN o_orderstatus = 'F' THEN 'archive' ELSE 'keep open' END AS o2 FROM orders),
t AS (SELECT *, 'As the ' || c1 || ', ' || o1 || '.' || CASE WHEN o_orderkey % 3 = 0 THEN '' ELSE ' As the ' || c2 || ', ' || o2 || '.' END AS text FROM r),
k AS (SELECT *, (contains(lower(text), lower(c1)) AND contains(lower(text), lower(o1)))::INT + (contains(lower(text), lower(c2)) AND contains(lower(text), lower(o2)))::INT AS told FROM t)
SELECT o_orderkey, '(' || c1 || ', ' || o1 || '), (' || c2 || ', ' || o2 || ')' AS expl_text, CASE WHEN told = 2 THEN 2 WHEN told > 0 THEN 1 ELSE 0 END AS c FROM k"""


def alignment() -> str:
    """The reference metric, token by token."""
    words = lambda t, at: f"SELECT k, w, {at}, row_number() OVER (PARTITION BY k, w ORDER BY {at}) AS j FROM (SELECT k, unnest(ws) AS w, unnest(range(0, len(ws))) AS {at} FROM (SELECT k, regexp_extract_all(lower({t}), '[a-z0-9]+') AS ws FROM pr))"
    return f"""{POOL},
{grid_ctes('e.place <= 5')},
pr AS MATERIALIZED (SELECT gt.k, technique, gt.text, hand.text AS reference FROM gt JOIN hand USING (style, row_id) WHERE technique IN (1, 4, 8)),
wa AS MATERIALIZED ({words('text', 'i')}), wb AS MATERIALIZED ({words('reference', 'r')}),
bt AS MATERIALIZED (SELECT *, CASE WHEN i = lag(i) OVER (PARTITION BY k ORDER BY i) + 1 AND r = lag(r) OVER (PARTITION BY k ORDER BY i) + 1 THEN 0 ELSE 1 END AS fresh FROM wa JOIN wb USING (k, w, j)),
sc AS (SELECT pr.k, technique, coalesce(m, 0) AS m, coalesce(ch, 0) AS ch, na, nb FROM pr LEFT JOIN (SELECT k, count(*) AS m, sum(fresh) AS ch FROM bt GROUP BY k) USING (k) JOIN (SELECT k, count(*) AS na FROM wa GROUP BY k) USING (k) JOIN (SELECT k, count(*) AS nb FROM wb GROUP BY k) USING (k)),
sv AS (SELECT technique, m, ch, CASE WHEN m = 0 THEN 0.0::DOUBLE ELSE (1 + 9.0::DOUBLE) * (m / na) * (m / nb) / ((m / nb) + 9.0::DOUBLE * (m / na)) * (1.0::DOUBLE - 0.5::DOUBLE * pow(ch / m, 3.0::DOUBLE)) END AS score FROM sc)
SELECT technique, count(*) AS n, sum(m)::BIGINT AS matches, sum(ch)::BIGINT AS chunks, sum(CAST(floor(score * 1000 + 0.5) AS BIGINT)) / 1000 AS score FROM sv GROUP BY technique"""


def judged() -> str:
    """The grid under a judge that errs once in twenty draws."""
    draw = lambda m, top: f"list_transform(range(1, 6), lambda i: CASE WHEN {uniform(f'concat_ws(chr(124), {quoted(m)}, style, row_id, technique, i)')} < 0.05 THEN {top} - {m} ELSE {m} END)"
    alert = lambda d: f"list_max(list_transform(list_distinct({d}), lambda y: len(list_filter({d}, lambda z: z = y)))) < 4"
    means = MEANS.replace("sum(CAST(floor(a *", "sum(CAST(floor(ma *").replace("sum(CAST(floor(c *", "sum(CAST(floor(mc *").replace("sum(CAST(floor(f *", "sum(CAST(floor(mf *").replace("sum(CAST(floor(total *", "sum(CAST(floor(mt *")
    return f"""{GRID},
dr AS (SELECT *, {draw('a', 1)} AS da, {draw('c', 2)} AS dc, {draw('f', 4)} AS df FROM gg),
md AS (SELECT *, list_sum(da) / 5.0::DOUBLE AS ma, list_sum(dc) / 5.0::DOUBLE AS mc, list_sum(df) / 5.0::DOUBLE AS mf FROM dr),
mt AS (SELECT *, {WEIGHTS['a']}::DOUBLE * ma + {WEIGHTS['f']}::DOUBLE * mf + {WEIGHTS['c']}::DOUBLE * mc + {WEIGHTS['s']}::DOUBLE * s AS mt FROM md)
SELECT technique, count(*) AS n, sum(({alert('da')} OR {alert('dc')} OR {alert('df')})::INT)::BIGINT AS alerts, {means} FROM mt GROUP BY technique"""


def noisy_texts(seed: int = 7, p: float = 0.3) -> str:
    from narrative_engine.operators.writing import SWAPS

    text = "text"
    for up, down in SWAPS:
        text = f"replace(replace(replace({text}, '{up}', chr(2)), '{down}', '{up}'), chr(2), '{down}')"
    wrong = f"{uniform(f'concat_ws(chr(124), {quoted(str(seed))}, style, row_id)')} < {p}"
    return f"nt AS MATERIALIZED (SELECT k, style, row_id, technique, mistake, CASE WHEN mistake THEN {text} ELSE text END AS text FROM (SELECT *, {wrong} AS mistake FROM gt WHERE technique = 5))"


def noisy_grid(by: str, more: str = "") -> str:
    return f"""{TEXTS},
{noisy_texts()},
nx AS (SELECT k, place, feature, value, value_num, contribution FROM nt JOIN ex USING (style, row_id)),
{claims_ctes('nt', 'nx', 'n_')},
{graded_cte('ng', 'nt', 'n_', 's.technique, s.mistake')}
SELECT {by}, count(*) AS n, {more}{MEANS} FROM ng GROUP BY {by}"""


WORDS_OF_BASE = values("wb", "base, words", [(b, len(t.split())) for b, t in BASE_PROMPTS.items()])
ORACLES: dict[str, str] = {
    "exemplar_summary": f"{ENTRIES}\nSELECT style, domain, count(*) AS entries, count(*) FILTER (WHERE place <= 5) AS hand_written, count(*) FILTER (WHERE place > {SET_ASIDE}) AS evaluated FROM e GROUP BY style, domain",
    "bootstrap_pool": f"{POOL}\nSELECT style, b::INT AS b, r::INT AS round, row_id, text FROM pool",
    "bootstrap_accept_rate": f"""{POOL},
c AS (SELECT style, count(*) AS candidates FROM bg GROUP BY style), a AS (SELECT style, count(*) AS accepted FROM acc GROUP BY style), p AS (SELECT style, count(*) AS in_pool, max(r)::INT AS rounds_used FROM pool GROUP BY style)
SELECT style, candidates, coalesce(accepted, 0) AS accepted, coalesce(in_pool, 0) AS in_pool, coalesce(rounds_used, 0) AS rounds_used, coalesce(in_pool, 0) >= {BOOT} AS reached FROM c LEFT JOIN a USING (style) LEFT JOIN p USING (style)""",
    "grid_scores": f"{GRID}\n{SCORES}",
    "grid_by_dataset": f"{GRID}\nSELECT technique, style, count(*) AS n, {MEANS} FROM gg GROUP BY GROUPING SETS ((technique), (style), (technique, style))",
    "grid_spread": f"{GRID},\n{spread('gg', 'technique', 'style')}\nSELECT * FROM outr JOIN inn USING (technique)",
    "top_setting_by_dataset": f"{GRID},\ntop2 AS (SELECT * FROM gg WHERE technique IN (7, 8)),\n{spread('top2', 'style', 'technique')},\nmn AS (SELECT style, count(*) AS n, {MEANS} FROM top2 GROUP BY style)\nSELECT mn.*, {', '.join(f'{n}_over_narratives' for n in UNIT)} FROM mn JOIN (SELECT * EXCLUDE (n) FROM inn) USING (style)",
    "base_prompt_scores": f"{SCORED}, {WORDS_OF_BASE}\nSELECT base, words, accuracy, completeness, row_number() OVER (ORDER BY (accuracy + completeness >= 7.5) DESC, words) = 1 AS chosen FROM scores JOIN wb USING (base) WHERE h = 0 AND b = 0",
    "grid_best": f"{SCORED}\nSELECT metric, technique, score, CASE WHEN u > 3.5 THEN 'high' WHEN u < 3 THEN 'low' ELSE 'middle' END AS band FROM (SELECT *, CASE WHEN metric = 'total' THEN score / 4 ELSE score END AS u, row_number() OVER (PARTITION BY metric ORDER BY score DESC, technique) AS r FROM long) WHERE r = 1",
    "grid_heatmap": f"{SCORED}\nSELECT metric, h, {', '.join(f'max(score) FILTER (WHERE b = {b}) AS b{b}' for b in (0, 1, 3, 5))} FROM long WHERE technique NOT IN (2, 3) GROUP BY metric, h",
    "grid_correlations": f"{SCORED},\nlu AS (SELECT metric, h::BIGINT AS h, b::BIGINT AS b, CAST(floor(score * 10000 + 0.5) AS BIGINT) AS u FROM long WHERE h > 0)\nSELECT metric, {half_up(pearson('h', 'u'), 3)} AS with_h, {half_up(pearson('b', 'u'), 3)} AS with_b FROM lu GROUP BY metric",
    "weight_sensitivity": f"{SCORED},\nws AS ({' UNION ALL '.join(f'SELECT {quoted(n)} AS weights, technique, {half_up('(' + ' + '.join(f'{m} * {x}' for m, x in zip(UNIT, w)) + f') / {sum(w)}', 4)} AS score FROM scores' for n, w in MEAN_OF_METRICS.items())})\nSELECT *, rank() OVER (PARTITION BY weights ORDER BY score DESC) AS place FROM ws",
    "guardrail_batch": f"{GRID}\nSELECT technique, count(*) AS n, count(*) FILTER (WHERE total < 14) AS rejected, min(total) FILTER (WHERE total >= 14) AS least_shown FROM gg GROUP BY technique",
    "grid_judge": judged(),
    "noisy_backend_scores": noisy_grid("mistake", "sum((a = 0)::INT)::BIGINT AS inaccurate, "),
    "replayed_model": noisy_grid("technique"),
    "reference_metric": alignment(),
    **validation("accuracy"), **validation("completeness"),
    "policy_revision": revised("accuracy", ACCURACY_GRADES, f",\n{claims_ctes('pt', 'px', 'z_', tolerance=0.0)},\nt0 AS (SELECT k, a AS a0 FROM z_v)"),
    "policy_revision_completeness": revised("completeness", COMPLETENESS_GRADES),
    "grader_correlation": correlation(),
    "completeness_checklists": f"{pairs('completeness')}\nSELECT category, count(*) AS n, sum(mentioned::INT)::BIGINT AS listed, sum(has_value::INT)::BIGINT AS value, sum((way <> 0)::INT)::BIGINT AS direction, sum((has_value AND way <> 0)::INT)::BIGINT AS done FROM pr JOIN p_g USING (k) GROUP BY category",
    "style_gap_sweep": f"{gaps()},\nla AS (SELECT *, {half_up('gap - lag(gap) OVER (ORDER BY n)', 4)} AS gain FROM ga)\nSELECT *, n = coalesce(max(CASE WHEN gain >= 0.05 THEN n END) OVER (), min(n) OVER ()) AS enough FROM la",
    "style_gap_unmasked": f"{gaps(False)}\nSELECT * FROM ga",
    "fluency_policies": fluency_forms(),
    "length_rules": f"""{HAND},
lw AS (SELECT style, max({WORDS.format('text')} / 3.0::DOUBLE) * 0.9::DOUBLE AS ratio, max(list_max(list_transform(string_split_regex(text, '[.;!?](?:\\s|$)|, while |, but '), lambda c: {WORDS.format('c')}::DOUBLE))) * 0.9::DOUBLE AS clause FROM hand GROUP BY style)
SELECT style, 'ratio' AS rule, {half_up('ratio', 4)} AS longest FROM lw UNION ALL SELECT style, 'clause', {half_up('clause', 4)} FROM lw""",
    "comparative_ablation": comparatives(),
    "new_application": f"WITH {top_ctes('activity')},\n{SIGNATURES}\nSELECT min(row_id) AS row_id, signature, count(*) AS n FROM sg GROUP BY signature ORDER BY n DESC, signature LIMIT 5",
    "new_application_shown": day_texts(),
    "regression_direction_positive": positive_features(),
    "direct_explain_accuracy": direct(),
    "explanation_round_trip": f"WITH {top_ctes('spend')}\nSELECT row_id, (place - 1)::INT AS at, feature, value, contribution FROM top",
    "explanation_extras": extras(),
    "rule_narratives": RULES,
    "pipeline_samples": user_style("", "SELECT k AS row_id, text AS narrative FROM n"),
}
