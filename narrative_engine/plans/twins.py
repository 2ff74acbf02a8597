"""DuckDB twins of the engine's deterministic queries, written relationally (long form, no arrays in the row)."""

from __future__ import annotations

from narrative_engine.operators import claims as cl
from narrative_engine.sources.tables import CATEGORICAL, LABEL_RULES, NUMERIC, features_sql


def effects_ctes(domain: str, p: str = "") -> str:
    """CTEs ``f`` (frame), ``num`` and ``cat`` (cards), their names prefixed by ``p``."""
    parts = [f"{p}f AS MATERIALIZED ({features_sql(domain)})"]
    if NUMERIC[domain]:
        one = [
            f"SELECT '{c}' AS feature, count(*)::DOUBLE AS n, sum({c})::DOUBLE AS sx, sum(target)::DOUBLE AS sy, sum(CAST({c} * target AS DECIMAL(34,6)))::DOUBLE AS sxy, sum(CAST({c} * {c} AS DECIMAL(34,6)))::DOUBLE AS sxx FROM {p}f"
            for c in NUMERIC[domain]
        ]
        parts.append(f"{p}sums AS (" + " UNION ALL ".join(one) + ")")
        parts.append(f"{p}num AS MATERIALIZED (SELECT feature, CASE WHEN n * sxx - sx * sx = 0 THEN 0.0::DOUBLE ELSE (n * sxy - sx * sy) / (n * sxx - sx * sx) END AS slope, sx / n AS mean FROM {p}sums)")
    if CATEGORICAL[domain]:
        parts.append(f"{p}whole AS (SELECT sum(target)::DOUBLE / count(*)::DOUBLE AS mean FROM {p}f)")
        one = [f"SELECT '{c}' AS feature, coalesce({c}, 'none') AS level, sum(target)::DOUBLE / count(*)::DOUBLE - (SELECT mean FROM {p}whole) AS effect FROM {p}f GROUP BY 2" for c in CATEGORICAL[domain]]
        parts.append(f"{p}cat AS MATERIALIZED (" + " UNION ALL ".join(one) + ")")
    return ",\n".join(parts)


def effects(domain: str) -> str:
    rows = []
    if NUMERIC[domain]:
        rows.append("SELECT feature, NULL::VARCHAR AS level, floor(slope * 1000.0::DOUBLE + 0.5) / 1000.0::DOUBLE AS effect, floor(mean * 1000.0::DOUBLE + 0.5) / 1000.0::DOUBLE AS mean FROM num")
    if CATEGORICAL[domain]:
        rows.append("SELECT feature, level, floor(effect * 1000.0::DOUBLE + 0.5) / 1000.0::DOUBLE AS effect, NULL::DOUBLE AS mean FROM cat")
    return f"WITH {effects_ctes(domain)}\n" + " UNION ALL ".join(rows)


def top_ctes(domain: str, n: int = 3, p: str = "") -> str:
    """… and ``attr`` (a row per feature) and ``top`` (the ranked ones)."""
    rows = []
    for c in NUMERIC[domain]:
        value = f"regexp_replace(regexp_replace(CAST({c} AS VARCHAR), '(\\.[0-9]*?)0+$', '\\1'), '\\.$', '')"
        rows.append(
            f"SELECT row_id, '{c.replace('_', ' ')}' AS feature, {value} AS value, {c}::DOUBLE AS value_num, floor(slope * ({c}::DOUBLE - mean) * 100.0::DOUBLE + 0.5) / 100.0::DOUBLE AS contribution FROM {p}f, {p}num WHERE feature = '{c}'"
        )
    for c in CATEGORICAL[domain]:
        rows.append(
            f"SELECT row_id, '{c.replace('_', ' ')}' AS feature, coalesce({c}, 'none') AS value, NULL::DOUBLE AS value_num, floor(effect * 100.0::DOUBLE + 0.5) / 100.0::DOUBLE AS contribution FROM {p}f JOIN {p}cat ON feature = '{c}' AND level = coalesce({c}, 'none')"
        )
    ranked = f"SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY abs(contribution) DESC, feature) AS place FROM {p}attr"
    return f"{effects_ctes(domain, p)},\n{p}attr AS ({' UNION ALL '.join(rows)}),\n{p}top AS MATERIALIZED (SELECT * FROM ({ranked}) WHERE place <= {n})"


TUPLES = "string_agg('(' || feature || ', ' || value || ', ' || printf('%.2f', contribution + 0.0) || ')', ', ' ORDER BY place)"


def explanations(domain: str) -> str:
    return f"WITH {top_ctes(domain)}\nSELECT row_id, {TUPLES} AS expl_text, count(*)::INT AS n_features FROM top GROUP BY row_id"


def long_top(domain: str) -> str:
    return f"WITH {top_ctes(domain)}\nSELECT row_id, feature, contribution, CAST(place AS INT) AS place FROM top"


def quoted(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def filled(slots: str, up: str, down: str) -> str:
    """A clause's text; the arguments are SQL, and feature, value and contribution are columns."""
    size = "abs(contribution)"
    whole = lambda k: f"CAST(CAST(floor({size} / {k} + 0.5) * {k} AS BIGINT) AS VARCHAR)"
    about = f"CASE WHEN {size} >= 10000 THEN {whole(1000)} WHEN {size} >= 1000 THEN {whole(100)} WHEN {size} >= 100 THEN {whole(10)} WHEN {size} >= 10 THEN {whole(1)} ELSE printf('%.2f', {size}) END"
    coarse = f"printf('%.2f', floor({size} * 140 + 1.0) / 100)"
    out = slots
    for slot, text in (("{d}", f"CASE WHEN contribution < 0 THEN {down} ELSE {up} END"), ("{c}", f"printf('%.2f', {size})"), ("{r}", about), ("{k}", coarse), ("{v}", "value"), ("{f}", "feature")):
        out = f"replace({out}, '{slot}', {text})"
    return out


OTHER = r"[^\p{L}\p{N}_.,;!?%\s-]"


def tokens_of(text: str) -> str:
    t = f"regexp_replace(lower({text}), '[$€£|]', '', 'g')"
    for _ in range(2):
        t = f"regexp_replace({t}, '([0-9]),([0-9]{{3}})', '\\1\\2', 'g')"
    t = f"replace(regexp_replace({t}, '{OTHER}', ' ', 'g'), ',', ' , ')"
    t = f"regexp_replace({t}, '[.;!?]+(\\s|$)', ' | ', 'g')"
    t = f"' ' || regexp_replace(regexp_replace({t}, '^\\s+|\\s+$', '', 'g'), '\\s+', '  ', 'g') || ' '"
    for word in cl.CONTRAST:
        t = f"replace({t}, '{cl.spaced(word)}', ' | ')"
    return t


def coded(t: str, reading: cl.Reading = cl.Reading()) -> str:
    for word in cl.GREATER_BEFORE:
        t = f"replace({t}, ' {word}  @', ' @g@  @')"
    for word in cl.SMALLER_BEFORE:
        t = f"replace({t}, ' {word}  @', ' @s@  @')"
    for phrases, code in ((cl.GREATER, " @g@ "), (cl.SMALLER, " @s@ "), (reading.up, " @u@ "), (reading.down, " @d@ "), (cl.UP, " @u@ "), (cl.DOWN, " @d@ "), (cl.ABSENT, " @n@ "), (cl.ROUNDED, "")):
        for phrase in sorted(phrases, key=lambda p: (-len(p), p)):
            t = f"replace({t}, '{cl.spaced(phrase)}', '{code}')"
    return t


def claims_ctes(n: str, x: str, p: str = "", tolerance: float = 0.05, usual: str = "NULL::DOUBLE") -> str:
    """CTEs that read texts ``n`` (k, text) against features ``x`` (k, place from 1, feature, value, value_num, contribution).

    They end in ``{p}g``, a record per feature, and ``{p}v`` (k, a, c, invented).  ``usual`` is SQL for a feature's usual value.
    """
    near = lambda v: f"coalesce(abs(num - abs({v})) <= abs({v}) * {tolerance}::DOUBLE + 1e-9, false)"
    number = "coalesce(value_num, TRY_CAST(value AS DOUBLE))"
    pad = "' ' || regexp_replace(trim(lower(feature)), '\\s+', '  ', 'g') || ' '"
    literal = f"' ' || regexp_replace(trim(replace(regexp_replace(lower(value), '{OTHER}', ' ', 'g'), ',', ' , ')), '\\s+', '  ', 'g') || ' '"
    nones = ", ".join(f"'{v}'" for v in cl.NONE_VALUES)
    return f"""{p}x AS MATERIALIZED (SELECT *, '@' || (place - 1) || '@' AS own, {number} AS number, {usual} AS usual FROM {x}),
{p}names AS (SELECT k, list({pad} || chr(31) || ' ' || own || ' ' ORDER BY length(feature) DESC, {pad}, own) AS names FROM {p}x GROUP BY k),
{p}t0 AS MATERIALIZED (SELECT k, {tokens_of('text')} AS t FROM {n}),
{p}t AS MATERIALIZED (SELECT k, list_reduce(list_concat([t], names), lambda acc, e: replace(acc, split_part(e, chr(31), 1), split_part(e, chr(31), 2))) AS t FROM {p}t0 JOIN {p}names USING (k)),
{p}c AS MATERIALIZED (SELECT k, ci, string_split(t, '|')[ci] AS base, string_split(code, '|')[ci] AS code FROM (SELECT k, t, code, unnest(range(1, len(string_split(t, '|')) + 1)) AS ci FROM (SELECT k, t, {coded('t')} AS code FROM {p}t))),
{p}tk AS (SELECT k, ci, ts, unnest(range(1, len(ts) + 1)) AS i FROM (SELECT k, ci, string_split_regex(trim(code), ' +') AS ts FROM {p}c)),
{p}items AS MATERIALIZED (SELECT k, ci, i, ts[i] AS tok, coalesce(ts[i - 1] = 'by', false) AS byf, len(list_filter(ts[1:i - 1], lambda y: y IN (',', 'and'))) AS part FROM {p}tk WHERE starts_with(ts[i], '@') OR regexp_matches(ts[i], '{cl.NUMBER_TOKEN}')),
{p}m AS MATERIALIZED (SELECT * FROM {p}items WHERE regexp_matches(tok, '^@[0-9]+@$')),
{p}q AS MATERIALIZED (
  SELECT k, ci, i, byf, num, owner FROM (
    SELECT q.k, q.ci, q.i, q.byf, abs(CAST(replace(q.tok, '%', '') AS DOUBLE)) AS num, m.tok AS owner,
      row_number() OVER (PARTITION BY q.k, q.ci, q.i ORDER BY CASE WHEN m.tok IS NULL THEN 9 WHEN m.part = q.part THEN 0 WHEN m.i < q.i THEN 1 ELSE 2 END, abs(m.i - q.i), m.i, m.tok) AS r
    FROM {p}items q LEFT JOIN {p}m m ON m.k = q.k AND m.ci = q.ci WHERE NOT starts_with(q.tok, '@')) WHERE r = 1),
{p}nf AS MATERIALIZED (
  SELECT k, place, bool_or(isv AND NOT (byf AND isc)) AS told_value, bool_or(exv AND NOT (byf AND isc)) AS exact_value, bool_or(isc AND (byf OR NOT isv)) AS told_contrib, bool_or(NOT (isv OR isc)) AS wrong_number
  FROM (SELECT x.k, x.place, q.byf, {near('number')} AS isv, {near('contribution')} AS isc, coalesce(num = abs(number), false) AS exv FROM {p}x x JOIN {p}q q ON q.k = x.k AND q.owner = x.own) GROUP BY k, place),
{p}cue AS (SELECT m.k, m.ci, m.i, arg_min(u.tok, u.i) FILTER (WHERE u.i > m.i) AS aft, arg_max(u.tok, u.i) FILTER (WHERE u.i < m.i) AS bef FROM {p}m m JOIN {p}items u ON u.k = m.k AND u.ci = m.ci AND u.tok IN ('@u@', '@d@') GROUP BY m.k, m.ci, m.i),
{p}neg AS (SELECT m.k, m.ci, m.i, bool_or(abs(u.i - m.i) <= 4) AS close, bool_or(m.i - u.i BETWEEN 1 AND 2) AS before FROM {p}m m JOIN {p}items u ON u.k = m.k AND u.ci = m.ci AND u.tok = '@n@' GROUP BY m.k, m.ci, m.i),
{p}cmp AS (SELECT m.k, m.tok, arg_min(u.tok, m.ci * 1000000000 + m.i * 10000 + u.i) AS compared FROM {p}m m JOIN {p}items u ON u.k = m.k AND u.ci = m.ci AND u.tok IN ('@g@', '@s@') AND (u.i > m.i OR u.i = m.i - 1) GROUP BY m.k, m.tok),
{p}mf AS MATERIALIZED (
  SELECT x.k, x.place, count(*) AS n_m, bool_or(contains(c.base, {literal})) AS spoken, bool_or(contains(c.base, ' yes ')) AS yes, bool_or(coalesce(neg.close, false)) AS close, bool_or(coalesce(neg.before, false)) AS before,
    count(coalesce(aft, bef)) AS n_way, bool_and(CASE WHEN coalesce(aft, bef) IS NULL THEN true ELSE (coalesce(aft, bef) = '@u@') = (contribution >= 0) END) AS all_right
  FROM {p}x x JOIN {p}m m ON m.k = x.k AND m.tok = x.own JOIN {p}c c ON c.k = m.k AND c.ci = m.ci LEFT JOIN {p}cue cue ON cue.k = m.k AND cue.ci = m.ci AND cue.i = m.i LEFT JOIN {p}neg neg ON neg.k = m.k AND neg.ci = m.ci AND neg.i = m.i GROUP BY x.k, x.place),
{p}g0 AS (
  SELECT x.k, x.place, x.feature, coalesce(n_m, 0) > 0 AS mentioned, coalesce(told_value, false) AS told_value, coalesce(told_contrib, false) AS contribution_told, coalesce(wrong_number, false) AS wrong_number,
    coalesce(spoken, false) AS spoken, coalesce(close, false) AS close, coalesce(before, false) AS before, coalesce(yes, false) AS yes, value_num IS NULL AS categorical, coalesce(value_num = 0, false) AS zero, lower(value) IN ({nones}) AS is_none,
    CASE WHEN coalesce(n_way, 0) = 0 THEN 0 WHEN all_right THEN 1 ELSE -1 END AS way, coalesce((compared = '@g@' AND value_num < usual) OR (compared = '@s@' AND value_num > usual), false) AS wrong_compared
  FROM {p}x x LEFT JOIN {p}nf nf USING (k, place) LEFT JOIN {p}mf mf USING (k, place) LEFT JOIN {p}cmp cmp ON cmp.k = x.k AND cmp.tok = x.own),
{p}g AS MATERIALIZED (
  SELECT *, CASE WHEN categorical THEN spoken OR told_value OR (is_none AND close) ELSE told_value OR (zero AND close) END AS has_value,
    wrong_number OR (categorical AND ((NOT is_none AND before AND NOT spoken) OR (is_none AND yes))) OR wrong_compared AS wrong FROM {p}g0),
{p}loose AS (SELECT DISTINCT q.k FROM {p}q q WHERE q.owner IS NULL AND NOT EXISTS (SELECT 1 FROM {p}x x WHERE x.k = q.k AND ({near('x.number')} OR {near('x.contribution')}))),
{p}v AS MATERIALIZED (
  SELECT g.k, CASE WHEN bool_or(wrong OR way < 0) OR bool_or(l.k IS NOT NULL) THEN 0 ELSE 1 END AS a, CASE WHEN bool_or(NOT mentioned) THEN 0 WHEN bool_and(has_value AND way <> 0) THEN 2 ELSE 1 END AS c, bool_or(l.k IS NOT NULL) AS invented
  FROM {p}g g LEFT JOIN {p}loose l ON l.k = g.k GROUP BY g.k)"""


WORDS = "len(regexp_extract_all({}, '[^ \\t\\n\\r]+'))"


def concise(words: str, room: str) -> str:
    return f"CASE WHEN {room} <= 0 OR {words} >= 2 * ({room}) THEN 0.0::DOUBLE WHEN {words} <= {room} THEN 4.0::DOUBLE ELSE 4.0::DOUBLE * (2.0::DOUBLE - {words} / ({room})) END"


def told(lead: str, slots: str, up: str, down: str, joiner: str, tail: str, source: str = "top", key: str = "row_id") -> str:
    """Texts (k, text, m) of ``source`` in one wording."""
    fill = filled(quoted(slots), quoted(up), quoted(down))
    return f"SELECT {key} AS k, {quoted(lead)} || string_agg({fill}, {quoted(joiner)} ORDER BY place) || {quoted(tail)} AS text, count(*) AS m FROM {source} GROUP BY {key}"


def zero_shot_ctes(domain: str) -> str:
    from narrative_engine.fixtures import ZERO_SHOT

    lead, slots, up, down, joiner, tail = ZERO_SHOT["plain"]
    words = WORDS.format("text")
    return f"""{top_ctes(domain)},
n AS MATERIALIZED ({told(lead, slots, up, down, joiner, tail)}), tx AS (SELECT row_id AS k, * FROM top),
{claims_ctes('n', 'tx')},
s AS (SELECT k, text, a, c, {words}::INT AS n_words, {concise(words, 'm * 30.0::DOUBLE')} AS s FROM n JOIN v USING (k))"""


def zero_shot(domain: str) -> str:
    """Zero-shot prose of the shortest base prompt, its grades and the guard."""
    return f"""WITH {zero_shot_ctes(domain)}
SELECT k AS row_id, text, a::INT AS a, c::INT AS c, n_words, floor(s * 1000 + 0.5) / 1000 AS s, floor((4.0 * a + 2.0 * c + s) * 1000 + 0.5) / 1000 AS total, 4.0 * a + 2.0 * c + s < 10.5 AS rejected FROM s"""


def guarded_days() -> str:
    return f"WITH {zero_shot_ctes('activity')}\nSELECT a::INT AS a, c::INT AS c, 4.0 * a + 2.0 * c + s < 10.5 AS rejected, count(*) AS n FROM s GROUP BY 1, 2, 3"


def label_agreement() -> str:
    """Labels against plain rules of the text: agreement and its chance-corrected form."""
    return f"""WITH w AS (SELECT toxic, quality, CASE WHEN {LABEL_RULES['toxic']} THEN 1 ELSE 0 END AS toxic_rule, CASE WHEN {LABEL_RULES['quality']} THEN 1 ELSE 0 END AS quality_rule FROM labels l JOIN documents d ON d.doc_id = l.doc_id),
v(metric, human, grader, n) AS (
  SELECT 'toxic', toxic, toxic_rule, count(*) FROM w GROUP BY toxic, toxic_rule UNION ALL SELECT 'quality', quality, quality_rule, count(*) FROM w GROUP BY quality, quality_rule),
t AS (SELECT metric, sum(n)::DOUBLE AS al, sum(CASE WHEN human = grader THEN n ELSE 0 END)::DOUBLE AS same FROM v GROUP BY metric),
h AS (SELECT metric, human AS k, sum(n) AS a FROM v GROUP BY metric, human), g AS (SELECT metric, grader AS k, sum(n) AS b FROM v GROUP BY metric, grader),
x AS (SELECT metric, sum(a * b)::DOUBLE AS x FROM h JOIN g USING (metric, k) GROUP BY metric)
SELECT metric, al::BIGINT AS n, floor(same / al * 10000 + 0.5) / 10000 AS agreement, floor((same / al - x / (al * al)) / (1 - x / (al * al)) * 10000 + 0.5) / 10000 AS kappa FROM t JOIN x USING (metric)"""


DOCUMENT_TOTALS = """WITH v AS (
  SELECT CAST(doc_id AS VARCHAR) AS name, length(regexp_replace(text, '[^A-Za-z]', '', 'g'))::DOUBLE AS a, length(regexp_replace(text, '[^0-9]', '', 'g'))::DOUBLE AS c,
    length(regexp_replace(text, '[^ ]', '', 'g'))::DOUBLE AS f, length(regexp_replace(text, '[A-Za-z0-9 ]', '', 'g'))::DOUBLE AS s, n_chars::DOUBLE AS printed FROM documents)
SELECT name, floor((a + c + f + s) * 1000 + 0.5) / 1000 AS recomputed, printed, abs(a + c + f + s - printed) <= 0.0015 AS agrees FROM v"""


CONCISENESS_DOCS = """WITH w AS (SELECT lang, len(regexp_extract_all(text, '[^ \\t\\n\\r]+')) AS n FROM documents),
g AS (SELECT lang, CASE WHEN n >= 2 * 3 * 60.0::DOUBLE THEN 0.0::DOUBLE WHEN n <= 3 * 60.0::DOUBLE THEN 4.0::DOUBLE ELSE 4.0::DOUBLE * (2.0::DOUBLE - n / (3 * 60.0::DOUBLE)) END AS s FROM w)
SELECT lang, count(*) AS n, count(*) FILTER (WHERE s = 0) AS n_zero, count(*) FILTER (WHERE s = 4) AS n_full, CAST(sum(CAST(floor(s * 1000 + 0.5) AS BIGINT)) AS BIGINT) AS thousandths FROM g GROUP BY lang"""
