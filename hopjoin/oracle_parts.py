"""SQL fragments for the oracles: the derived tables and the string measures, in DuckDB's dialect."""

from __future__ import annotations

from hopjoin.sources import fixtures as fx


def sql_list(values) -> str:
    return "[" + ", ".join("'" + v + "'" for v in values) + "]"


def drop_chars(c: str, k: str, n: int = 1, spread: int = 3) -> str:
    return f"(substring({c}, 1, 1 + ({k}) % {spread}) || substring({c}, 2 + ({k}) % {spread} + {n}))"


def reverse_parts(c: str) -> str:
    return f"array_to_string(list_reverse(string_split({c}, ' ')), ' ')"


PERSON = f"""CASE WHEN c_custkey < 500 THEN {sql_list(fx.GIVEN)}[(c_custkey % 20 + 1)::INT] || ' ' || {sql_list(fx.FAMILY)}[((c_custkey // 20) % 25 + 1)::INT]
    ELSE {sql_list(fx.GIVEN)}[(c_custkey % 20 + 1)::INT] || ' ' || {sql_list(fx.MIDDLE)}[((c_custkey // 500) % 12 + 1)::INT] || ' ' || {sql_list(fx.FAMILY)}[((c_custkey // 20) % 25 + 1)::INT] END"""

MISSPELL = "n"
for _a, _b in fx.MISSPELT.items():
    MISSPELL = f"CASE WHEN split_part(name, ' ', 2) = '{_a}' THEN split_part(name, ' ', 1) || ' {_b}' ELSE {MISSPELL} END"
MISSPELL = MISSPELL.replace("ELSE n END", "ELSE name END")

CTES = f"""
places AS (SELECT n_nationkey, {sql_list(fx.PLACES)}[(n_nationkey + 1)::INT] AS place_name, n_regionkey FROM nation),
survey AS (SELECT n_nationkey::INT AS survey_id, CASE n_nationkey % 4 WHEN 0 THEN place_name WHEN 1 THEN {reverse_parts('place_name')} WHEN 2 THEN {drop_chars('place_name', 'n_nationkey')}
    ELSE place_name || CASE WHEN (n_nationkey // 4) % 2 = 0 THEN ' Clinic' ELSE ' Hospital' END END AS territory_name, 4 + ((n_nationkey * 37) % 100) / 100.0::DOUBLE AS satisfaction FROM places WHERE n_nationkey % 6 <> 5),
people AS (SELECT c_custkey, {PERSON} AS person_name, c_nationkey FROM customer),
registry AS (SELECT c_custkey AS citizen_id, CASE c_custkey % 4 WHEN 0 THEN person_name
    WHEN 1 THEN string_split(person_name, ' ')[-1] || ' ' || array_to_string(string_split(person_name, ' ')[1:-2], ' ')
    WHEN 2 THEN {drop_chars('person_name', 'c_custkey')} ELSE {drop_chars('person_name', 'c_custkey', 2)} END AS resident_name, (c_custkey % 7)::INT AS household FROM people WHERE c_custkey % 5 <> 4),
pnames AS (SELECT p_name AS name, row_number() OVER (ORDER BY p_name) - 1 AS k FROM (SELECT DISTINCT p_name FROM part WHERE p_name IS NOT NULL)),
watch AS (SELECT k::INT AS watch_id, name, CASE k % 5 WHEN 0 THEN name WHEN 1 THEN {reverse_parts('name')} WHEN 2 THEN {drop_chars('name', 'k')} WHEN 3 THEN name || ' Item' ELSE {MISSPELL} END AS item_name, (k % 3)::INT AS risk FROM pnames)"""


def token_sort(c: str) -> str:
    return f"array_to_string(list_sort(list_filter(regexp_split_to_array({c}, '\\s+'), lambda t: t <> '')), ' ')"


def lcs(a: str, b: str) -> str:
    """Nested list_reduce over one row of the table; the first list element is the start value."""
    inner = f"list_reduce(list_prepend([0::BIGINT], list_transform(range(1, length({b}) + 1), lambda j: [j])), lambda acc, y: list_append(acc, CASE WHEN substring({a}, x[1], 1) = substring({b}, y[1], 1) THEN prev[y[1]] + 1 ELSE greatest(prev[y[1] + 1], acc[y[1]]) END))"
    return f"list_extract(list_reduce(list_prepend(list_resize([0::BIGINT], (length({b}) + 1)::BIGINT, 0), list_transform(range(1, length({a}) + 1), lambda i: [i])), lambda prev, x: {inner}), length({b}) + 1)"


def ratio(a: str, b: str) -> str:
    return f"CASE WHEN length({a}) + length({b}) = 0 THEN 1.0 ELSE 2.0 * {lcs(a, b)} / (length({a}) + length({b})) END"


def dictionaries(x: str, xc: str, y: str, yc: str) -> str:
    """CTEs dx, dy (v, cnt, s) and pairs (x, cx, y, cy, sim)."""
    one = lambda t, c: f"SELECT {c} AS v, count(*) AS cnt, {token_sort(c)} AS s FROM {t} WHERE {c} IS NOT NULL GROUP BY {c}"
    return f"dx AS ({one(x, xc)}), dy AS ({one(y, yc)}), pairs AS (SELECT dx.v AS x, dx.cnt AS cx, dy.v AS y, dy.cnt AS cy, {ratio('dx.s', 'dy.s')} AS sim FROM dx, dy)"


def near_dictionaries(x: str, xc: str, y: str, yc: str, names: tuple[str, str, str] = ("dx", "dy", "pairs"), above: float | None = None) -> str:
    """The same CTEs for larger sides: pairs holds every pair that may be best for its x or its y (or, with `above`, reach it).

    With n the two lengths and e the edit distance, the ratio lies between 1 - 2 e / n and 1 - e / n.
    """
    dx, dy, pairs = names
    one = lambda t, c: f"SELECT {c} AS v, count(*) AS cnt, {token_sort(c)} AS s FROM {t} WHERE {c} IS NOT NULL GROUP BY {c}"
    bar = f"{above}" if above is not None else "least(lo_x, lo_y)"
    return f"""{dx} AS ({one(x, xc)}), {dy} AS ({one(y, yc)}),
    {pairs}_e AS (SELECT a.v AS x, a.cnt AS cx, b.v AS y, b.cnt AS cy, a.s AS sx, b.s AS sy, CASE WHEN length(a.s) + length(b.s) = 0 THEN 0.0 ELSE levenshtein(a.s, b.s) / (length(a.s) + length(b.s))::DOUBLE END AS far FROM {dx} a, {dy} b),
    {pairs}_c AS (SELECT * FROM (SELECT *, max(1 - 2 * far) OVER (PARTITION BY x) AS lo_x, max(1 - 2 * far) OVER (PARTITION BY y) AS lo_y FROM {pairs}_e) WHERE 1 - far >= {bar} - 1e-9),
    {pairs} AS (SELECT x, cx, y, cy, {ratio('sx', 'sy')} AS sim FROM {pairs}_c)"""


def fuzzy_edge(i: int, edge: str, x: str, xc: str, y: str, yc: str, bar: float) -> tuple[str, str]:
    """CTEs of one fuzzy edge and a row (edge_id, lr, rl, exact, fuzzy): scores, exact and one-to-one overlap above `bar`.

    The one-to-one assignment: values of one sorted form by rank, then mutually best pairs, then the greedy walk over what is left.
    """
    def pairs_of(name: str, a: str, b: str, keep: str) -> str:
        far = "CASE WHEN length(a.s) + length(b.s) = 0 THEN 0.0 ELSE levenshtein(a.s, b.s) / (length(a.s) + length(b.s))::DOUBLE END"
        return f"""{name}_e AS (SELECT a.v AS x, b.v AS y, a.s AS sx, b.s AS sy, {far} AS far FROM {a} a, {b} b),
    {name}_c AS (SELECT * FROM (SELECT *, max(1 - 2 * far) OVER (PARTITION BY x) AS lo_x, max(1 - 2 * far) OVER (PARTITION BY y) AS lo_y FROM {name}_e) WHERE 1 - far >= {keep} - 1e-9),
    {name} AS (SELECT *, CASE WHEN sim >= 1 THEN '' ELSE md5(x || '|' || y) END AS tie FROM (SELECT x, y, {ratio('sx', 'sy')} AS sim FROM {name}_c) WHERE sim > {bar})"""

    form = lambda side: f"SELECT v, s, row_number() OVER (PARTITION BY s ORDER BY v) AS rn FROM d{side}{i}"
    rest = lambda side, taken, of: f"SELECT v, s FROM {of} WHERE v NOT IN (SELECT {side} FROM {taken})"
    ctes = f"""{near_dictionaries(x, xc, y, yc, (f'dx{i}', f'dy{i}', f'p{i}'))},
    f{i} AS (SELECT a.v AS x, b.v AS y FROM ({form('x')}) a JOIN ({form('y')}) b ON a.s = b.s AND a.rn = b.rn),
    ax{i} AS ({rest('x', f'f{i}', f'dx{i}')}), ay{i} AS ({rest('y', f'f{i}', f'dy{i}')}), {pairs_of(f'q{i}', f'ax{i}', f'ay{i}', 'least(lo_x, lo_y)')},
    m{i} AS (SELECT x, y FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY sim DESC, tie, x, y) AS rx, row_number() OVER (PARTITION BY y ORDER BY sim DESC, tie, x, y) AS ry FROM q{i}) WHERE rx = 1 AND ry = 1),
    bx{i} AS ({rest('x', f'm{i}', f'ax{i}')}), by{i} AS ({rest('y', f'm{i}', f'ay{i}')}), {pairs_of(f'w{i}', f'bx{i}', f'by{i}', str(bar))},
    o{i} AS MATERIALIZED (SELECT x, y, row_number() OVER (ORDER BY sim DESC, tie, x, y) AS i FROM w{i}),
    g{i} AS (SELECT 0::BIGINT AS i, []::VARCHAR[] AS xs, []::VARCHAR[] AS ys
      UNION ALL SELECT o.i, CASE WHEN list_contains(xs, o.x) OR list_contains(ys, o.y) THEN xs ELSE list_append(xs, o.x) END, CASE WHEN list_contains(xs, o.x) OR list_contains(ys, o.y) THEN ys ELSE list_append(ys, o.y) END FROM g{i} JOIN o{i} o ON o.i = g{i}.i + 1),
    n{i} AS (SELECT (SELECT count(*) FROM f{i}) + (SELECT count(*) FROM m{i}) + (SELECT max(len(xs)) FROM g{i}) AS m, (SELECT count(*) FROM dx{i}) AS l, (SELECT count(*) FROM dy{i}) AS r, (SELECT count(*) FROM dx{i} WHERE v IN (SELECT v FROM dy{i})) AS both_)"""
    mean = lambda v, c: f"(SELECT sum({c} * m) / sum({c}) FROM (SELECT {v}, {c}, max(sim) AS m FROM p{i} GROUP BY {v}, {c}))"
    row = f"SELECT '{edge}' AS edge_id, {mean('x', 'cx')} AS lr, {mean('y', 'cy')} AS rl, both_ / (l + r - both_)::DOUBLE AS exact, m / (l + r - m)::DOUBLE AS fuzzy FROM n{i}"
    return ctes, row


def plain_edge(i: int, edge: str, x: str, xc: str, y: str, yc: str) -> tuple[str, str]:
    """The same for columns that are compared by equality."""
    ctes = f"dx{i} AS (SELECT {xc}::VARCHAR AS v, count(*) AS cnt FROM {x} WHERE {xc} IS NOT NULL GROUP BY 1), dy{i} AS (SELECT {yc}::VARCHAR AS v, count(*) AS cnt FROM {y} WHERE {yc} IS NOT NULL GROUP BY 1)"
    share = lambda a, b: f"(SELECT coalesce(sum(cnt) FILTER (WHERE v IN (SELECT v FROM {b}{i})), 0) / sum(cnt)::DOUBLE FROM {a}{i})"
    both = f"(SELECT count(*) FROM dx{i} WHERE v IN (SELECT v FROM dy{i}))"
    exact = f"{both} / ((SELECT count(*) FROM dx{i}) + (SELECT count(*) FROM dy{i}) - {both})::DOUBLE"
    return ctes, f"SELECT '{edge}' AS edge_id, {share('dx', 'dy')} AS lr, {share('dy', 'dx')} AS rl, {exact} AS exact, {exact} AS fuzzy"


def edges(rows: list[tuple[str, str, str, str, str]]) -> str:
    """One row per key edge with n_common, n_left, n_right, overlap."""
    parts = []
    for db, a, x, b, y in rows:
        (l, lc), (r, rc) = sorted([(f"{db}.{a}", x), (f"{db}.{b}", y)], key=lambda p: p[0])
        lt, rt = l.split(".")[1], r.split(".")[1]
        parts.append(f"""SELECT '{l}({lc})~{r}({rc})' AS edge_id, '{l}' AS left_node, '{lc}' AS left_column, '{r}' AS right_node, '{rc}' AS right_column,
            (SELECT count(*) FROM (SELECT {lc}::VARCHAR FROM {lt} WHERE {lc} IS NOT NULL INTERSECT SELECT {rc}::VARCHAR FROM {rt})) AS n_common,
            (SELECT count(DISTINCT {lc}) FROM {lt}) AS n_left, (SELECT count(DISTINCT {rc}) FROM {rt}) AS n_right""")
    return "SELECT *, coalesce(n_common / nullif(n_left + n_right - n_common, 0)::DOUBLE, 0.0) AS overlap FROM (" + " UNION ALL ".join(parts) + ")"
