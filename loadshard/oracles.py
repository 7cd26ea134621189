"""DuckDB SQL for the queries. Query texts are read with the library's parser; mapping, joins and filters are SQL of its own.

Each pattern reads a materialised relation of its own property, so that no query touches tables it does not name."""

from __future__ import annotations

import re

from loadshard.query.ast import Filter, Query, Term, TriplePattern, Var
from loadshard.workload.catalogue import SAMPLE, SAMPLE_TABLES, SAMPLE_THETA, crawl_load, query
from loadshard.workload.load import pattern_rows
from loadshard.query.parser import parse

#: table, subject, class, [(property column, object, kind)]
TABLES = (
    ("region", "'region:'||r_regionkey", "region", "r_name:str"),
    ("nation", "'nation:'||n_nationkey", "nation", "n_regionkey>region n_name:str"),
    ("customer", "'customer:'||c_custkey", "customer", "c_nationkey>nation c_name:str c_mktsegment:str c_acctbal:num"),
    ("supplier", "'supplier:'||s_suppkey", "supplier", "s_nationkey>nation s_name:str s_acctbal:num"),
    ("part", "'part:'||p_partkey", "part", "p_name:str p_brand:str p_type:str p_size:int p_retailprice:num"),
    ("orders", "'order:'||o_orderkey", "order", "o_custkey>customer o_orderstatus:str o_orderpriority:str o_totalprice:num o_orderdate:ts"),
    ("lineitem", "'line:'||l_orderkey||'/'||l_linenumber||'/'||l_partkey||'/'||l_suppkey", "line", "l_orderkey>order l_partkey>part l_suppkey>supplier l_linenumber:int l_quantity:num l_extendedprice:num l_discount:num l_tax:num l_returnflag:str l_linestatus:str l_shipdate:ts"),
    ("events", "'event:'||event_id", "event", "user_id>customer ts:ts event_type:str value:num k:json"),
    ("documents", "'doc:'||doc_id", "document", "source>source lang:str n_chars:int text:md5"),
    ("labels", "'doc:'||doc_id", None, "quality:int toxic:int"),
    ("pages", "'page:'||page_id", "page", "url:str html:md5"),
    ("benchmark", "'bench:'||item_id", "benchmark", "text:md5"),
    ("conversations", "'turn:'||conv_id||'/'||turn", "turn", "conv_id>conv turn:int role:str text:md5"),
    ("embeddings", "'vec:'||vec_id", "vector", "label:int"),
)


def branches(tables: tuple[str, ...] | None = None) -> list[tuple[str, str | None, str]]:
    """(property, class or None, SELECT) of each table's properties."""
    out = []
    for name, s, cls, spec in TABLES:
        if tables is not None and name not in tables:
            continue
        word = "SELECT DISTINCT" if name == "lineitem" else "SELECT"
        row = lambda p, o, k, n, c=None, word=word, s=s, name=name: f"{word} {s} AS s, '{p}' AS p, {o} AS o, '{k}' AS o_kind, {n} AS o_num FROM {name}" + (f" WHERE {c} IS NOT NULL" if c else "")
        if cls:
            out.append(("rdf:type", f"class:{cls}", row("rdf:type", f"'class:{cls}'", "iri", "NULL::DOUBLE")))
        for item in spec.split():
            if ">" in item:
                c, to = item.split(">")
                out.append((f"p:{c}", None, row(f"p:{c}", f"'{to}:'||{c}", "iri", "NULL::DOUBLE", c)))
                continue
            c, kind = item.split(":")
            text, k, number = {
                "str": (c, "str", "NULL::DOUBLE"), "md5": (f"md5({c})", "str", "NULL::DOUBLE"), "int": (f"CAST({c} AS VARCHAR)", "num", f"CAST({c} AS DOUBLE)"),
                "num": (f"CAST(CAST({c} AS DECIMAL(18,2)) AS VARCHAR)", "num", f"CAST(CAST({c} AS DECIMAL(18,2)) AS DOUBLE)"),
                "ts": (f"CAST(epoch_us({c}) AS VARCHAR)", "ts", f"CAST(epoch_us({c}) AS DOUBLE)"),
                "json": (f"json_extract_string(props, '$.{c}')", "num", f"CAST(json_extract_string(props, '$.{c}') AS DOUBLE)"),
            }[kind]
            out.append((f"p:{c}", None, row(f"p:{c}", text, k, number, "props" if kind == "json" else c)))
    return out


def tri(tables: tuple[str, ...] | None = None) -> str:
    """tri(s, p, o, o_kind, o_num) as a common table expression body."""
    return "tri AS MATERIALIZED (" + " UNION ALL ".join(sql for _, _, sql in branches(tables)) + ")"


def relation(t: TriplePattern) -> tuple[str, str]:
    """(name, body) of the rows that a pattern's property allows."""
    if isinstance(t.p, Var):
        return "tri", tri()
    cls = t.o.text if t.p.text == "rdf:type" and isinstance(t.o, Term) else None
    found = [sql for p, c, sql in branches() if p == t.p.text and (cls is None or c == cls)]
    name = "r_" + re.sub(r"\W", "_", t.p.text + (f"_{cls}" if cls else ""))
    return name, f"{name} AS MATERIALIZED (" + (" UNION ALL ".join(found) or "SELECT NULL::VARCHAR AS s, NULL::VARCHAR AS p, NULL::VARCHAR AS o, NULL::VARCHAR AS o_kind, NULL::DOUBLE AS o_num WHERE FALSE") + ")"


def quoted(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"


def _filter(f: Filter, at: dict[str, str]) -> str:
    if f.op in ("&&", "||"):
        a, b = (_filter(x, at) for x in f.args)
        return f"({a} {'AND' if f.op == '&&' else 'OR'} {b})"
    if f.op == "!":
        return f"NOT ({_filter(f.args[0], at)})"
    numeric = any(isinstance(x, Term) and x.kind == "num" for x in f.args)
    side = lambda x: (x.text if numeric else quoted(x.text)) if isinstance(x, Term) else (at[x.name].replace(".o", ".o_num") if numeric else at[x.name])
    a, b = f.args
    return f"{side(a)} {f.op} {side(b)}"


def bgp(q: Query) -> str:
    """Joins of the patterns' relations for a query; SELECT text without the WITH."""
    out = []
    names = q.output
    for g in q.branches:
        every = [(t, None) for t in g.required] + [(t, k) for k, part in enumerate(g.optional) for t in part]
        seats: dict[str, set[str]] = {}
        for t, _ in every:
            for c, x in t.parts():
                if isinstance(x, Var):
                    seats.setdefault(x.name, set()).add(c)
        at: dict[str, str] = {}
        text = ""
        where = []
        for i, (t, opt) in enumerate(every):
            cond = []
            for c, x in t.parts():
                me = f"t{i}.{c}"
                if isinstance(x, Term):
                    cond.append(f"{me} = {quoted(x.text)}")
                    if c == "o":
                        cond.append(f"t{i}.o_kind = '{x.kind}'")
                    continue
                if c == "o" and seats[x.name] != {"o"}:
                    cond.append(f"t{i}.o_kind = 'iri'")
                if x.name in at:
                    cond.append(f"{me} = {at[x.name]}")
                    if seats[x.name] == {"o"}:
                        cond.append(f"t{i}.o_kind = {at[x.name]}_kind")
                else:
                    at[x.name] = me
            if i == 0:
                text = f"{relation(t)[0]} t0"
                where += cond
            elif opt is None:
                text += f" JOIN {relation(t)[0]} t{i} ON {' AND '.join(cond) or 'TRUE'}"
            else:
                text += f" LEFT JOIN {relation(t)[0]} t{i} ON {' AND '.join(cond)}"
        where += [_filter(f, at) for f in g.filters]
        cols = ", ".join(f"{at[v]} AS {v}" if v in at else f"CAST(NULL AS VARCHAR) AS {v}" for v in names)
        out.append(f"SELECT {cols} FROM {text}" + (f" WHERE {' AND '.join(where)}" if where else ""))
    sql = " UNION ALL ".join(f"({x})" for x in out) if len(out) > 1 else out[0]
    if q.distinct:
        sql = f"SELECT DISTINCT * FROM ({sql})"
    if q.limit is not None:
        sql = f"SELECT * FROM ({sql}) ORDER BY {', '.join(k for k, _ in q.order)} LIMIT {q.limit} OFFSET {q.offset}"
    return sql


def of_query(qid: str) -> str:
    q = query(qid)
    every = dict(relation(t) for g in q.branches for t in [*g.required, *(x for part in g.optional for x in part)])
    return f"WITH {', '.join(every.values())} {bgp(q)}"


def values(rows: list[tuple], names: str) -> str:
    lit = lambda x: "NULL" if x is None else str(x).lower() if isinstance(x, bool) else str(x) if isinstance(x, int | float) else quoted(x)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) AS v({names})"


def load_cte(items: list[tuple[str, str, int]]) -> str:
    """load(query_id, weight, bgp_id, pattern_id, s, p, o, o_kind, s_var, p_var, o_var)."""
    rows = [r for qid, text, w in items for r in pattern_rows(parse(text, qid), w)]
    names = "query_id, weight, bgp_id, pattern_id, optional, s, p, o, o_kind, s_var, p_var, o_var"
    typed = ", ".join(c if c in ("weight", "bgp_id", "pattern_id", "optional") else f"CAST({c} AS VARCHAR) AS {c}" for c in names.split(", "))
    return f"load AS (SELECT {typed} FROM ({values(rows, names)}))"


TERMS = "terms AS (SELECT DISTINCT query_id, weight, s AS term, 'iri' AS kind FROM load WHERE s IS NOT NULL UNION SELECT DISTINCT query_id, weight, o, o_kind FROM load WHERE o IS NOT NULL), freq AS (SELECT term, kind, CAST(sum(weight) AS BIGINT) AS freq FROM terms GROUP BY ALL)"


def normalized(theta: int) -> str:
    return f"""norm AS (SELECT l.query_id, l.weight, l.bgp_id, l.pattern_id, CASE WHEN a.freq >= {theta} THEN l.s END AS s, l.p, CASE WHEN b.freq >= {theta} THEN l.o END AS o,
  CASE WHEN b.freq >= {theta} THEN l.o_kind END AS o_kind, l.s_var, l.p_var, l.o_var FROM load l LEFT JOIN freq a ON l.s = a.term AND a.kind = 'iri' LEFT JOIN freq b ON l.o = b.term AND l.o_kind = b.kind),
occ AS (SELECT *, coalesce(s, '_') || ' ' || coalesce(p, '_') || ' ' || coalesce(o, '_') || ' ' || coalesce(o_kind, '_') AS pattern FROM norm)"""


SEATS = "seats AS (SELECT query_id, weight, bgp_id, pattern_id, pattern, unnest(list_distinct(list_filter([s_var, p_var, o_var], lambda x: x IS NOT NULL))) AS v FROM occ)"
EDGE_SQL = "SELECT a, b, CAST(sum(weight) AS BIGINT) AS w FROM (SELECT DISTINCT x.query_id, x.weight, least(x.pattern, y.pattern) AS a, greatest(x.pattern, y.pattern) AS b FROM seats x JOIN seats y ON x.query_id = y.query_id AND x.bgp_id = y.bgp_id AND x.v = y.v AND x.pattern_id < y.pattern_id) GROUP BY a, b"
CRAWL = crawl_load()
ACCESS_PATHS = """, seen AS (SELECT query_id, pattern_id, list_filter([{'c': 's', 'v': s_var}, {'c': 'p', 'v': p_var}, {'c': 'o', 'v': o_var}], lambda x: x.v IS NOT NULL) AS free FROM load WHERE bgp_id = 0 AND NOT optional),
each AS (SELECT query_id, pattern_id, free, unnest(free) AS x FROM seen)
SELECT query_id AS query, CAST(pattern_id AS INTEGER) AS pattern, array_to_string(list_filter(['s', 'p', 'o'], lambda c: NOT list_contains(list_transform(free, lambda f: f.c), c)), '') || x.c || array_to_string(list_transform(list_filter(free, lambda f: f.c <> x.c), lambda f: f.c), '') AS path, x.v AS sorted_by FROM each"""


def pattern_counts(items: list[tuple[str, str, int]]) -> str:
    """met(p, o, o_kind, n): rows of the tables for each pattern of the queries' first branches, repeats included."""
    asked = {(t.p.text, t.o if isinstance(t.o, Term) else None) for qid, text, _ in items for t in parse(text, qid).branches[0].required}
    out = []
    for p, o in sorted(asked, key=str):
        found = [sql.replace("SELECT DISTINCT", "SELECT", 1) for q, c, sql in branches() if q == p and (c is None or o is None or o.text == c)]
        names, cond = (f"{quoted(o.text)} AS o, '{o.kind}' AS o_kind", f" WHERE o = {quoted(o.text)} AND o_kind = '{o.kind}'") if o else ("CAST(NULL AS VARCHAR) AS o, CAST(NULL AS VARCHAR) AS o_kind", "")
        out.append(f"SELECT {quoted(p)} AS p, {names}, count(*) AS n FROM ({' UNION ALL '.join(found)}){cond}")
    return f"met AS ({' UNION ALL '.join(out)}), told AS (SELECT l.query_id, l.pattern_id, met.n FROM load l JOIN met ON l.p = met.p AND l.o IS NOT DISTINCT FROM met.o AND l.o_kind IS NOT DISTINCT FROM met.o_kind WHERE l.bgp_id = 0 AND NOT l.optional)"


def access_paths() -> str:
    head, body = ACCESS_PATHS.rsplit("\nSELECT ", 1)
    return f"{head}, {pattern_counts(CRAWL)}\nSELECT {body.removesuffix(' FROM each')}, n FROM each JOIN told USING (query_id, pattern_id)"


def khop_local(rows: list[tuple[str, bool]]) -> str:
    return f"WITH {load_cte(CRAWL)}, {pattern_counts(CRAWL)} SELECT v.query, v.local, CAST(sum(n) AS BIGINT) AS n FROM ({values(rows, 'query, local')}) v JOIN told ON told.query_id = v.query GROUP BY ALL"

#: The sample load by brute force: every triple is labelled with all predicates that hold for it.
_PROPS = "(SELECT list(DISTINCT p) FROM norm WHERE p IS NOT NULL)"
_LABEL = f"""list_filter([CASE WHEN o_kind = 'num' AND o_num < 0 THEN 'o < 0' END, CASE WHEN o_kind = 'str' AND o = 'BUILDING' THEN 'o = BUILDING' END, CASE WHEN o_kind = 'iri' AND o = 'region:1' THEN 'o = region:1' END,
 CASE WHEN o_kind = 'num' AND o_num >= 9000 THEN 'o >= 9000' END, CASE WHEN list_contains({_PROPS}, p) THEN 'p = ' || p END], lambda x: x IS NOT NULL)"""
_SAMPLE = f"""{load_cte(SAMPLE)}, {TERMS}, {normalized(SAMPLE_THETA)}, {SEATS}, {tri(SAMPLE_TABLES)},
frag AS (SELECT parts, CASE WHEN len(parts) = 0 THEN 'all negated' ELSE array_to_string(parts, ' & ') END AS definition, count(*) AS size FROM (SELECT {_LABEL} AS parts FROM tri) GROUP BY 1),
pat AS (SELECT DISTINCT query_id, weight, pattern, list_filter(['p = ' || p, 'o = ' || o], lambda x: x IS NOT NULL) AS need FROM occ),
met AS (SELECT f.definition, f.parts, f.size, q.* FROM frag f LEFT JOIN pat q ON list_has_all(f.parts, q.need))"""
_FREQ = {
    "pattern_sum": "SELECT definition, size, CAST(coalesce(sum(weight), 0) AS BIGINT) AS freq FROM met GROUP BY ALL",
    "closest": "SELECT definition, size, CAST(coalesce(sum(CASE WHEN list_has_all(need, parts) THEN weight END), 0) AS BIGINT) AS freq FROM met GROUP BY ALL",
    "query_count": "SELECT definition, size, CAST(coalesce(sum(weight), 0) AS BIGINT) AS freq FROM (SELECT DISTINCT definition, size, query_id, weight FROM met) GROUP BY ALL",
}
_WITNESS = """wit AS (SELECT DISTINCT x.query_id, x.weight, least(x.pattern, y.pattern) AS a, greatest(x.pattern, y.pattern) AS b FROM seats x JOIN seats y ON x.query_id = y.query_id AND x.bgp_id = y.bgp_id AND x.v = y.v AND x.pattern_id < y.pattern_id),
over AS (SELECT DISTINCT pattern, definition FROM met WHERE pattern IS NOT NULL),
pair AS (SELECT DISTINCT w.query_id, w.weight, w.a AS pa, w.b AS pb, least(x.definition, y.definition) AS a, greatest(x.definition, y.definition) AS b FROM wit w JOIN over x ON w.a = x.pattern JOIN over y ON w.b = y.pattern WHERE x.definition <> y.definition)"""
_EDGE = {
    "edge_sum": "SELECT a, b, CAST(sum(weight) AS BIGINT) AS w FROM pair GROUP BY a, b",
    "query_count": "SELECT a, b, CAST(sum(weight) AS BIGINT) AS w FROM (SELECT DISTINCT query_id, weight, a, b FROM pair) GROUP BY a, b",
}
SAMPLE_PREDICATES = f"WITH {load_cte(SAMPLE)}, {TERMS}, {normalized(SAMPLE_THETA)}, {tri(SAMPLE_TABLES)}, pred AS (SELECT 'p' AS component, '=' AS op, p AS value FROM norm WHERE p IS NOT NULL UNION SELECT 'o', '=', o FROM norm WHERE o IS NOT NULL UNION SELECT * FROM (VALUES ('o', '<', '0'), ('o', '>=', '9000'))) SELECT component, op, value, (SELECT count(*) FROM tri WHERE CASE WHEN op = '<' THEN o_kind = 'num' AND o_num < 0 WHEN op = '>=' THEN o_kind = 'num' AND o_num >= 9000 WHEN component = 'p' THEN p = value ELSE o = value END) AS n FROM pred"
SAMPLE_MINTERMS = f"""WITH {_SAMPLE}, pred AS (SELECT DISTINCT 'p' AS c, p FROM norm WHERE p IS NOT NULL UNION SELECT DISTINCT 'o', o FROM norm WHERE o IS NOT NULL),
term AS (SELECT p, o, o_num FROM (SELECT p FROM pred WHERE c = 'p' UNION ALL SELECT 'other') CROSS JOIN (VALUES ('BUILDING', NULL), ('region:1', NULL), ('other', NULL), ('n', -1.0), ('n', 0.0), ('n', 1.0), ('n', 9000.0)) v(o, o_num)),
vec AS (SELECT DISTINCT p, CASE WHEN o IN ('BUILDING', 'region:1') THEN o END AS e, coalesce(o_num < 0, FALSE) AS low, coalesce(o_num >= 9000, FALSE) AS high FROM term)
SELECT 'sign vectors' AS what, CAST(2 ** ((SELECT count(*) FROM pred) + 2) AS BIGINT) AS n UNION ALL SELECT 'satisfiable', count(*) FROM vec UNION ALL SELECT 'satisfiable without ranges', count(*) FROM (SELECT DISTINCT p, e FROM vec) UNION ALL SELECT 'observed', count(*) FROM frag"""


def sample_frequency(mode: str) -> str:
    return f"WITH {_SAMPLE} SELECT definition, freq, size, freq * size AS load FROM ({_FREQ[mode]})"


def sample_edges(mode: str) -> str:
    return f"WITH {_SAMPLE}, {_WITNESS} {_EDGE[mode]}"


#: A site's score from its load l, the joins a with its fragments and their number c, and the uniform load u.
SCORES = {"smoothed": "2 * u / (u + l) * (1 + a)", "literal": "2 * u / (u + l) * (a + c)", "balance": "2 * u / (u + l)", "affinity": "1.0 + a", "damped": "2 * u / (u + l) * (1 + log2(1 + a))"}


def _steps(form: str) -> str:
    """Fragments in falling order of load, each to the first site of the best score; homes are a growing list."""
    here = lambda what: f"list_sum(list_transform(range(1, k + 1), lambda i: CASE WHEN homes[i] = s THEN {what} ELSE 0 END))"
    score = SCORES[form]
    for name, what in (("l", "loads[i]"), ("a", "joins[i]"), ("c", "1")):
        score = re.sub(rf"\b{name}\b", f"coalesce({here(what)}, 0)", score)
    return f"""WITH RECURSIVE {_SAMPLE}, {_WITNESS}, e AS ({_EDGE['edge_sum']}), sized AS (SELECT definition, freq * size AS load FROM ({_FREQ['pattern_sum']}) WHERE definition <> 'all negated'),
ord AS (SELECT CAST(row_number() OVER (ORDER BY load DESC, definition) AS INTEGER) AS turn, definition, load FROM sized),
bag AS (SELECT list(load ORDER BY turn) AS loads, CAST(sum(load) AS DOUBLE) / 3 AS u FROM ord),
near AS (SELECT x.turn, list(CAST(coalesce(e.w, 0) AS BIGINT) ORDER BY y.turn) AS joins FROM ord x CROSS JOIN ord y LEFT JOIN e ON e.a = least(x.definition, y.definition) AND e.b = greatest(x.definition, y.definition) GROUP BY x.turn),
step AS (SELECT 0 AS k, CAST([] AS INTEGER[]) AS homes, CAST([] AS DOUBLE[]) AS scores UNION ALL
 SELECT k + 1, list_append(homes, CAST(list_position(now, list_max(now)) AS INTEGER)), now FROM (SELECT k, homes, list_transform([1, 2, 3], lambda s: CAST({score} AS DOUBLE)) AS now FROM step JOIN near ON near.turn = step.k + 1, bag))"""


def sample_trace(form: str) -> str:
    return f"{_steps(form)} SELECT turn, definition, round(scores[1], 3) AS site1, round(scores[2], 3) AS site2, round(scores[3], 3) AS site3, homes[turn] AS chosen FROM step JOIN ord ON ord.turn = step.k"


def sample_allocation(form: str) -> str:
    return f"{_steps(form)}, home AS (SELECT homes[turn] AS site_id, definition, load FROM step JOIN ord ON ord.turn = step.k) SELECT CAST(n.i AS INTEGER) AS site_id, coalesce(string_agg(definition, '; ' ORDER BY definition), '') AS fragments, CAST(coalesce(sum(load), 0) AS BIGINT) AS load FROM range(1, 4) n(i) LEFT JOIN home ON home.site_id = n.i GROUP BY n.i"
