"""DuckDB SQL that finds by brute force, from the given tables, what the methods find: boundaries, keys, dependencies."""

from __future__ import annotations

from collections.abc import Sequence

from tabqa.sources import corpus

#: The relations of the handbook.
W = f"WITH {corpus.BASE_SQL} "
#: The relations, and its grids cell by cell.
CELLS = f"{W}, {corpus.CELLS_SQL} "

#: Columns of the handbook's relations, in the order of their tables' attributes.
COLUMNS = {"pair_codes": ["brand", "nation", "code"], "zones": ["nation", "zone"], "zone_counts": ["code", "zone", "pairs"], "limits": ["size_code", "code", "min", "nom", "max"], "trade": ["nation", "yr", "qty", "cents"]}
LABELS = {name: [x for x in labels if x] for name, labels in corpus.LABELS.items()}

MASK = "translate(regexp_replace(regexp_replace(regexp_replace({0}, '\\p{{L}}+', chr(1), 'g'), '\\p{{Nd}}+', chr(2), 'g'), '[^\\x01\\x02]+', chr(3), 'g'), chr(1) || chr(2) || chr(3), 'ADN')"
_PLAIN = MASK.format("regexp_replace(txt, '\\s+', '', 'g')")

_LINES = {"top": ("c", "r"), "left": ("r", "c"), "bottom": ("c", "last_r - r"), "right": ("r", "last_c - c")}


def boundary(side: str, rule: str = "repeat", prefix: str = "") -> str:
    """CTEs up to `{prefix}start` (table_id, v): where data start from a side; the rule is tried at every place of every line."""
    line, place = _LINES[side]
    p = prefix
    ordered = f"""
{p}m AS (SELECT table_id, {line} AS line, {place} AS place, {_PLAIN} AS m FROM cells JOIN (SELECT table_id, max(r) AS last_r, max(c) AS last_c FROM cells GROUP BY 1) USING (table_id) WHERE lower(trim(txt)) NOT IN ('', 'n/a', 'na', '-', '–')),
{p}o AS (SELECT *, row_number() OVER (PARTITION BY table_id, line ORDER BY place) AS i FROM {p}m),
{p}change AS (SELECT a.* FROM {p}o a JOIN {p}o b ON a.table_id = b.table_id AND a.line = b.line AND b.i = a.i - 1 WHERE a.m <> b.m)"""
    if rule == "repeat":
        fit = f"""
{p}e AS (SELECT a.table_id, a.line, a.i, q.p, a.m = b.m AS same FROM {p}o a CROSS JOIN (SELECT unnest([1, 2, 3]) AS p) q JOIN {p}o b ON a.table_id = b.table_id AND a.line = b.line AND b.i = a.i + q.p),
{p}fit AS (SELECT x.table_id, x.line, x.place FROM {p}change x JOIN {p}e f ON f.table_id = x.table_id AND f.line = x.line AND f.i = x.i AND f.same
    JOIN {p}e g ON g.table_id = x.table_id AND g.line = x.line AND g.p = f.p AND g.i >= x.i GROUP BY x.table_id, x.line, x.place, f.p HAVING avg(CAST(g.same AS INTEGER)) >= 0.5)"""
    else:
        fit = f"""
{p}fit AS (SELECT x.table_id, x.line, x.place FROM {p}change x JOIN {p}o k ON k.table_id = x.table_id AND k.line = x.line AND k.i >= x.i GROUP BY x.table_id, x.line, x.place HAVING avg(CAST(k.m = x.m AS INTEGER)) >= 0.8)"""
    return f"""{ordered},{fit},
{p}votes AS (SELECT table_id, v, count(*) AS n FROM (SELECT table_id, line, min(place) AS v FROM {p}fit GROUP BY ALL) GROUP BY ALL),
{p}best AS (SELECT table_id, v FROM {p}votes QUALIFY row_number() OVER (PARTITION BY table_id ORDER BY n DESC, v) = 1),
{p}start AS (SELECT t.table_id, coalesce(v, 0) AS v FROM (SELECT DISTINCT table_id FROM cells) t LEFT JOIN {p}best USING (table_id))"""


def boundary_sql(side: str, name: str, rule: str = "repeat") -> str:
    return f"{CELLS}, {boundary(side, rule)} SELECT table_id, CAST(v AS INTEGER) AS {name} FROM start"


def counts(relation: str, columns: Sequence[str], prefix: str = "") -> str:
    """CTEs `{prefix}d` (bits, d): distinct tuples of every set of columns, the first column being the highest bit; `{prefix}n` (n): distinct rows."""
    listed, p = ", ".join(columns), prefix
    return f"""
{p}g AS (SELECT GROUPING({listed}) AS g FROM {relation} GROUP BY CUBE({listed})),
{p}d AS (SELECT CAST({2 ** len(columns) - 1} - g AS BIGINT) AS bits, count(*) AS d FROM {p}g GROUP BY 1),
{p}n AS (SELECT d AS n FROM {p}d WHERE bits = {2 ** len(columns) - 1}),
{p}k AS (SELECT bits FROM {p}d, {p}n WHERE d = n AND bits <> 0),
{p}minimal AS (SELECT bits FROM {p}k a WHERE NOT EXISTS (SELECT 1 FROM {p}k b WHERE b.bits <> a.bits AND b.bits & a.bits = b.bits))"""


def names_of(bits: str, names: Sequence[str]) -> str:
    """The names of a set, sorted and joined by commas."""
    parts = [f"CASE WHEN {bits} & {1 << (len(names) - 1 - i)} <> 0 THEN '{n}' END" for i, n in enumerate(names)]
    return f"array_to_string(list_sort(list_filter([{', '.join(parts)}], lambda x: x IS NOT NULL)), ',')"


def keys_sql(relation: str, columns: Sequence[str], base: str = "WITH ") -> str:
    """(table_id, attrs, size): all minimal keys of a relation."""
    return f"{base}{counts(relation, columns)} SELECT '{relation}' AS table_id, {names_of('bits', columns)} AS attrs, CAST(bit_count(bits) AS INTEGER) AS size FROM minimal"


def fds(columns: Sequence[str], most: int, prefix: str = "") -> str:
    """A query over the counts of `prefix` for (lhs, a): bits of minimal left sides that are no keys, and of what they determine."""
    p, singles = prefix, ", ".join(str(1 << i) for i in range(len(columns)))
    return f"""SELECT x.bits AS lhs, a FROM {p}d x CROSS JOIN {p}n CROSS JOIN (SELECT unnest([{singles}]) AS a) JOIN {p}d y ON y.bits = x.bits | a AND y.d = x.d
WHERE x.bits & a = 0 AND bit_count(x.bits) BETWEEN 1 AND {most} AND x.d < n
AND NOT EXISTS (SELECT 1 FROM {p}d s JOIN {p}d t ON t.bits = s.bits | a AND t.d = s.d WHERE s.bits <> 0 AND s.bits <> x.bits AND s.bits & x.bits = s.bits)"""


def _value(column: str) -> str:
    return f"regexp_replace(lower(CAST({column} AS VARCHAR)), '^0+([0-9])', '\\1')"


#: CTE `long` (table_id, row_id, attr, val): the handbook's relations value by value.
LONG = ", ".join(f"{t}_rows AS MATERIALIZED (SELECT row_number() OVER () AS row_id, * FROM {t})" for t in COLUMNS) + ", long AS MATERIALIZED (" + " UNION ALL ".join(
    f"SELECT '{t}' AS table_id, row_id, '{t}.{label}' AS attr, {_value(c)} AS val FROM {t}_rows" for t, cs in COLUMNS.items() for c, label in zip(cs, LABELS[t], strict=True)
) + ")"

#: CTEs `unary` (lhs_table, lhs, rhs_table, rhs) and `pairs` (the same with two attributes on both sides): inclusions, by counting.
INCLUSIONS = """
one AS MATERIALIZED (SELECT DISTINCT table_id, attr, val FROM long),
one_n AS (SELECT attr, count(*) AS n FROM one GROUP BY 1),
unary AS MATERIALIZED (SELECT a.table_id AS lhs_table, a.attr AS lhs, b.table_id AS rhs_table, b.attr AS rhs FROM one a JOIN one b ON a.val = b.val AND a.table_id <> b.table_id JOIN one_n ON one_n.attr = a.attr GROUP BY ALL HAVING count(*) = any_value(n)),
two AS MATERIALIZED (SELECT DISTINCT x.table_id, x.attr AS a1, y.attr AS a2, x.val AS v1, y.val AS v2 FROM long x JOIN long y ON x.table_id = y.table_id AND x.row_id = y.row_id AND x.attr <> y.attr),
two_n AS (SELECT a1, a2, count(*) AS n FROM two GROUP BY ALL),
pairs AS (SELECT p.table_id AS lhs_table, p.a1, p.a2, q.table_id AS rhs_table, q.a1 AS b1, q.a2 AS b2 FROM two p JOIN two q ON p.v1 = q.v1 AND p.v2 = q.v2 AND p.table_id <> q.table_id JOIN two_n ON two_n.a1 = p.a1 AND two_n.a2 = p.a2 WHERE p.a1 < p.a2 GROUP BY ALL HAVING count(*) = any_value(n))"""

#: CTE `labels` (table_id, label): what the handbook's attributes are called.
LABELLED = "labels(table_id, label) AS (VALUES " + ", ".join(f"('{t}', '{x}')" for t, xs in LABELS.items() for x in xs) + ")"
