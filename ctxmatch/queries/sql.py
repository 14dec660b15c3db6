"""Common SQL of the oracles: scenario metadata as VALUES, graph and path CTEs, sentences, word hashes."""

from __future__ import annotations

from ..sources.scenarios import RESIDUE, SCENARIO, SPECS, Schema, columns_of, derived_sql, order_of, truth


def lit(x) -> str:
    return "NULL" if x is None else str(x) if isinstance(x, (int, bool)) else "'" + str(x).replace("'", "''") + "'"


def values(rows) -> str:
    return "VALUES " + ", ".join("(" + ", ".join(map(lit, r)) + ")" for r in rows)


def catalog_cte(specs: list[Schema]) -> str:
    cols = [(s.name, t, f"{s.name}.{t}.{c}", c, o, d, pk, ref and ref[0], ref and ref[1]) for s in specs for t, c, o, d, pk, ref, _ in s.columns]
    raw = [(s.name, *r) for s in specs for r in s.refs]
    return (
        f"cols(schema_id, table_id, column_id, column_name, ordinal, dtype, is_pk, fk_table, fk_column) AS ({values(cols)}),\n"
        f"raw_refs(schema_id, strong_table, strong_column, weak_table, weak_column) AS ({values(raw) if raw else 'SELECT NULL, NULL, NULL, NULL, NULL WHERE false'}),\n"
        "refs AS (SELECT DISTINCT * FROM raw_refs WHERE strong_table <> weak_table),\n"
        "tabs AS (SELECT schema_id, table_id, count(*) AS n_cols FROM cols GROUP BY ALL)"
    )


ALL = [SPECS[s] for s in (*SCENARIO, "corpus")]
FOUR = [SPECS[s] for s in SCENARIO]


#: The retail tables whose keys and references are found in their rows; the columns with their types, in order.
FOUND = {t: columns_of("star", t) for t in ("region", "nation", "supplier", "customer", "part", "orders")}


def found_cte() -> str:
    """The CTEs of ``catalog_cte`` for the schema ``given``, with keys and references from the rows of the tables."""
    whole = [(t, c) for t, cs in FOUND.items() for c, d in cs if d in ("int", "bigint")]
    names = values([("given", t, f"given.{t}.{c}", c, o, d) for t, cs in FOUND.items() for o, (c, d) in enumerate(cs, 1)])
    seen = " UNION ALL ".join(f"SELECT '{t}', '{c}', count({c}), count(DISTINCT {c}), count(*) > 0 AND count(*) = count(DISTINCT {c}) FROM {t}" for t, c in whole)
    cells = " UNION ALL ".join(f"SELECT DISTINCT '{t}', '{c}', {c}::BIGINT FROM {t} WHERE {c} IS NOT NULL" for t, c in whole)
    return (
        f"named(schema_id, table_id, column_id, column_name, ordinal, dtype) AS ({names}),\n"
        f"seen(t, c, n_rows, n, k) AS ({seen}),\ncells(t, c, v) AS ({cells}),\n"
        "held AS (SELECT w.t AS wt, w.c AS wc, s.t AS st, s.c AS sc, min(y.n) AS n FROM cells w JOIN cells s ON w.v = s.v AND w.t <> s.t JOIN seen x ON x.t = w.t AND x.c = w.c AND NOT x.k JOIN seen y ON y.t = s.t AND y.c = s.c AND y.k GROUP BY ALL HAVING count(*) = min(x.n)),\n"
        "one AS (SELECT wt, wc, arg_min(st, (n, st, sc)) AS st, arg_min(sc, (n, st, sc)) AS sc FROM held GROUP BY ALL),\n"
        "cols AS (SELECT a.*, coalesce(k, false) AS is_pk, st AS fk_table, sc AS fk_column FROM named a LEFT JOIN seen ON t = a.table_id AND c = a.column_name LEFT JOIN one ON wt = a.table_id AND wc = a.column_name),\n"
        "refs AS (SELECT schema_id, fk_table AS strong_table, fk_column AS strong_column, table_id AS weak_table, column_name AS weak_column FROM cols WHERE fk_table IS NOT NULL),\n"
        "tabs AS (SELECT schema_id, table_id, count(*) AS n_cols FROM cols GROUP BY ALL)"
    )


def edges_cte(modes: tuple[str, ...] = ("directed",)) -> str:
    down, up = "SELECT schema_id, '{m}' AS mode, strong_table AS src, weak_table AS dst FROM refs", "SELECT schema_id, '{m}' AS mode, weak_table AS src, strong_table AS dst FROM refs"
    parts = [x.format(m=m) for m in modes for x in ({"directed": [down], "inverse": [up], "undirected": [down, up]}[m])]
    return "edges AS (" + " UNION ".join(parts) + ")"


def views_cte(d_max: int, modes: tuple[str, ...] = ("directed",), ties: str = "one") -> str:
    """All simple paths by recursion, then the shortest of each ordered pair; the engine instead grows settled shortest paths."""
    modes_sql = ", ".join(f"('{m}')" for m in modes)
    choose = "min(path)" if ties == "one" else "path"
    return (
        edges_cte(modes) + ",\n"
        f"walk AS (SELECT schema_id, mode, table_id AS src, table_id AS dst, [table_id] AS path FROM tabs, (VALUES {modes_sql}) AS m(mode)\n"
        f"  UNION ALL SELECT w.schema_id, w.mode, w.src, e.dst, list_append(w.path, e.dst) FROM walk w JOIN edges e ON e.schema_id = w.schema_id AND e.mode = w.mode AND e.src = w.dst\n"
        f"  WHERE len(w.path) < {d_max} AND NOT list_contains(w.path, e.dst)),\n"
        "least AS (SELECT schema_id, mode, src, dst, min(len(path)) AS n FROM walk GROUP BY ALL),\n"
        f"views AS (SELECT w.schema_id, w.mode, w.src, w.dst, {choose} AS path FROM walk w JOIN least l ON w.schema_id = l.schema_id AND w.mode = l.mode AND w.src = l.src AND w.dst = l.dst AND len(w.path) = l.n"
        + (" GROUP BY w.schema_id, w.mode, w.src, w.dst)" if ties == "one" else ")")
    )


NEIGHBOURS = (
    "near AS (SELECT t.schema_id, t.table_id, coalesce((SELECT list_sort(list(DISTINCT weak_table)) FROM refs r WHERE r.schema_id = t.schema_id AND r.strong_table = t.table_id), []) AS weak,"
    " coalesce((SELECT list_sort(list(DISTINCT strong_table)) FROM refs r WHERE r.schema_id = t.schema_id AND r.weak_table = t.table_id), []) AS strong FROM tabs t)"
)
CONSTRAINT = (
    "CASE WHEN is_pk AND fk_table IS NOT NULL THEN 'primary key and foreign key references table ' || fk_table || ' column ' || fk_column"
    " WHEN is_pk THEN 'primary key' WHEN fk_table IS NOT NULL THEN 'foreign key references table ' || fk_table || ' column ' || fk_column END"
)
CONTEXT = (
    "ctx AS (SELECT v.schema_id, array_to_string(v.path, '>') AS view_id,"
    " list_sort(list_filter(list_distinct(flatten(list(n.weak))), lambda x: NOT list_contains(v.path, x))) AS weak,"
    " list_sort(list_filter(list_distinct(flatten(list(n.strong))), lambda x: NOT list_contains(v.path, x))) AS strong"
    " FROM (SELECT schema_id, path, unnest(path) AS table_id FROM views) v JOIN near n ON n.schema_id = v.schema_id AND n.table_id = v.table_id GROUP BY v.schema_id, v.path)"
)
RAC = (
    "rac AS (SELECT v.schema_id, array_to_string(v.path, '>') AS view_id, v.path, v.pos - 1 AS position, array_to_string(v.path, ' ') AS view_name, v.origin AS origin_table, c.column_id, c.column_name, c.dtype,"
    f" {CONSTRAINT} AS con FROM (SELECT schema_id, path, unnest(path) AS origin, generate_subscripts(path, 1) AS pos FROM views) v"
    " JOIN cols c ON c.schema_id = v.schema_id AND c.table_id = v.origin)"
)


def values_cte(specs: list[Schema]) -> str:
    """vals(column_id, v): up to five values of each column, as a list; the engine takes the rows with TakeOrderedAndProject."""
    parts = []
    for s in specs:
        for t in s.tables:
            cols, order = columns_of(s.name, t), ", ".join(f"{c} ASC NULLS LAST" for c in order_of(s.name, t))
            shown = {"double": "printf('%.2f', {c})", "timestamp": "strftime({c}, '%Y-%m-%d')", "array<float>": "array_to_string([printf('%.2f', x::DOUBLE) for x in {c}[1:3]], ' ')"}
            items = ", ".join(f"{{'c': '{s.name}.{t}.{c}', 'v': {shown.get(d, "array_to_string(string_split(CAST({c} AS VARCHAR), ' ')[1:300], ' ')").format(c=c)}}}" for c, d in cols)
            parts.append(f"SELECT unnest([{items}]) AS x, _n FROM (SELECT *, row_number() OVER (ORDER BY {order}) AS _n FROM ({derived_sql(s.name, t)}) WHERE _key IS NULL OR _key % 4 = {RESIDUE[s.name]} QUALIFY _n <= 5)")
    return "cells AS (" + " UNION ALL ".join(parts) + "),\nvals AS (SELECT x.c AS column_id, list(x.v ORDER BY _n) AS v FROM cells WHERE x.v IS NOT NULL GROUP BY 1)"


def sentence(kind: str, missing: str = "None") -> str:
    """The sentence of rac rows joined with ctx (weak, strong) and vals (v)."""
    show = lambda word, x: f"'{word} ' || coalesce(nullif({x}, ''), '{missing}')"
    cut = lambda x, n: f"array_to_string(string_split({x}, ' ')[1:{n}], ' ')"
    parts = [show("column", "column_name"), show("table", "view_name"), show("type", "dtype"), show("constraint", "con")]
    if kind == "NOTAB":
        del parts[1]
    if kind != "META":
        parts.append(show("values", cut("array_to_string(coalesce(v, [])[1:5], ', ')", 300)))
    if kind == "REF":
        parts += [show("weak tables", "array_to_string(weak, ', ')"), show("strong tables", "array_to_string(strong, ', ')")]
    return cut("'[CLS] ' || " + " || ' [SEP] ' || ".join(parts), 512)


TABDOC = (
    "tabdoc AS (SELECT schema_id, table_id, '[CLS] table ' || table_id"
    " || ' [SEP] keys ' || coalesce(nullif(array_to_string(list(column_name || ' ' || dtype ORDER BY ordinal) FILTER (is_pk), ', '), ''), 'None')"
    " || ' [SEP] foreign keys ' || coalesce(nullif(array_to_string(list(column_name || ' ' || dtype || ' references ' || fk_table || ' ' || fk_column ORDER BY ordinal) FILTER (fk_table IS NOT NULL), ', '), ''), 'None')"
    " || ' [SEP] columns ' || coalesce(nullif(array_to_string(list(column_name || ' ' || dtype ORDER BY ordinal) FILTER (NOT is_pk AND fk_table IS NULL), ', '), ''), 'None') AS text FROM cols GROUP BY schema_id, table_id)"
)


def buckets(source: str, key: str, dim: int = 64, name: str = "hash") -> str:
    """CTEs ending in ``name``(key, bucket, value): the word-hash encoder. ``source``: (key, text)."""
    return (
        f"{name}_words AS (SELECT {key}, w, count(*) AS n FROM (SELECT {key}, unnest(regexp_extract_all(lower(text), '[a-z0-9]+')) AS w FROM {source}) GROUP BY ALL),\n"
        f"{name}_cells AS (SELECT {key}, (('0x' || substr(md5(w), 1, 8))::BIGINT % {dim})::INT AS bucket, round(sum(CASE WHEN substr(md5(w), 9, 1) < '8' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END * sqrt(n::DOUBLE)), 9) AS raw FROM {name}_words GROUP BY ALL),\n"
        f"{name} AS (SELECT {key}, bucket, CASE WHEN nn > 0 THEN raw / nn ELSE 0 END AS value FROM (SELECT *, sqrt(sum(raw * raw) OVER (PARTITION BY {key})) AS nn FROM {name}_cells))"
    )


def cosine(s: str) -> str:
    """A rounded score; null (no common bucket) and minus zero are zero."""
    return f"CASE WHEN round({s}, 6) <> 0 THEN round({s}, 6) ELSE 0::DOUBLE END"


SIMDOC = (
    f"{catalog_cte(FOUR)},\n{views_cte(1)},\n{RAC},\n{TABDOC},\n"
    f"coltext AS (SELECT schema_id, column_id, {sentence('META')} AS text FROM rac),\n"
    + buckets("coltext", "schema_id, column_id", name="ch") + ",\n" + buckets("tabdoc", "schema_id, table_id", name="th") + ",\n"
    "sim AS (SELECT c.schema_id AS source_schema, c.column_id, t.schema_id AS target_schema, t.table_id, sum(c.value * t.value) AS s FROM ch c JOIN th t ON c.bucket = t.bucket AND c.schema_id <> t.schema_id GROUP BY ALL),\n"
    f"simdoc AS (SELECT c.schema_id AS source_schema, c.column_id, t.schema_id AS target_schema, t.table_id, {cosine('s')} AS score,"
    " row_number() OVER (PARTITION BY c.column_id, t.schema_id ORDER BY round(coalesce(s, 0), 6) DESC, t.table_id) AS rank"
    " FROM cols c JOIN tabs t ON c.schema_id <> t.schema_id LEFT JOIN sim x ON x.column_id = c.column_id AND x.target_schema = t.schema_id AND x.table_id = t.table_id)"
)
TRUTH = (
    f"pairs(schema_a, column_a, schema_b, column_b, kind) AS ({values(truth())}),\n"
    "truth AS (SELECT schema_a AS source_schema, column_a AS column_id, schema_b AS target_schema, column_b AS target_column, kind FROM pairs UNION ALL SELECT schema_b, column_b, schema_a, column_a, kind FROM pairs),\n"
    "truth_tables AS (SELECT DISTINCT source_schema, column_id, target_schema, string_split(target_column, '.')[2] AS table_id FROM truth)"
)
