"""DuckDB SQL of the operators that SQL can express."""

from __future__ import annotations

from loadshard.llm.urlrules import RULES

_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _host(u: str) -> str:
    return f"translate(coalesce(regexp_extract({u}, '(?s)\\A.*?://([^/?#]*)', 1), ''), '{_UP}', '{_LOW}')"


def _path(u: str) -> str:
    return f"coalesce(regexp_extract({u}, '(?s)\\A.*?://[^/?#]*([^?#]*)', 1), '')"


def _key(u: str) -> str:
    return f"CASE WHEN contains({u}, '://') THEN {_host(u)} || {_path(u)} || coalesce(regexp_extract({u}, '(?s)\\A[^#]*?(\\?[^#]*)', 1), '') END"


def _tags(tag: str, mark: str, value: str) -> str:
    return f"list_transform(list_filter(regexp_extract_all(html, '(?is)<{tag}\\b[^>]*>'), lambda x: regexp_matches(x, '(?is){mark}')), lambda x: regexp_extract(x, '(?is){value}', 1))"


_Q = "[\"'']?"
_LINKS = ", ".join(
    (
        _tags("link", f"\\brel\\s*=\\s*{_Q}canonical\\b", f"\\bhref\\s*=\\s*{_Q}([^\"''\\s>]+)"),
        _tags("meta", f"\\bhttp-equiv\\s*=\\s*{_Q}refresh\\b", f"\\bcontent\\s*=\\s*{_Q}\\s*\\d*\\s*;?\\s*url\\s*=\\s*{_Q}([^\"''\\s>]+)"),
        _tags("meta", f"\\bproperty\\s*=\\s*{_Q}og:url\\b", f"\\bcontent\\s*=\\s*{_Q}([^\"''\\s>]+)"),
    )
)
_RULES = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in RULES)
_FIT = "(n.host = r.rh OR suffix(n.host, '.' || r.rh)) AND starts_with(n.path, r.rp)"

URL_RULES = f"""WITH RECURSIVE rules AS (SELECT * FROM (VALUES {_RULES}) v(verdict, rh, rp)),
told AS (SELECT url AS u, replace(unnest(flatten([{_LINKS}])), '&amp;', '&') AS t FROM pages WHERE contains(url, '://')),
hop AS (SELECT u, CASE WHEN contains(t, '://') THEN t WHEN starts_with(t, '//') THEN regexp_extract(u, '(?s)\\A(.*?):', 1) || ':' || t
  WHEN starts_with(t, '/') THEN regexp_extract(u, '(?s)\\A(.*?://[^/?#]*)', 1) || t ELSE regexp_extract(u, '(?s)\\A(.*?://[^/?#]*)', 1) || regexp_extract({_path('u')}, '(?s)\\A(.*/)', 1) || t END AS v FROM told WHERE t <> ''),
e AS (SELECT {_key('u')} AS a, {_key('v')} AS b FROM hop), twoway AS (SELECT a, b FROM e WHERE a <> b UNION SELECT b, a FROM e WHERE a <> b),
reach AS (SELECT a, b FROM twoway UNION SELECT r.a, x.b FROM reach r JOIN twoway x ON r.b = x.a),
n AS (SELECT b AS key, {_host("'x://' || b")} AS host, {_path("'x://' || b")} AS path FROM (SELECT DISTINCT b FROM reach)),
node AS (SELECT n.key, arg_max(r.verdict, length(r.rh || r.rp) * 2 + (r.verdict = 'allow')::INT) AS verdict FROM n JOIN rules r ON {_FIT} GROUP BY n.key),
spread AS (SELECT reach.a AS key FROM reach JOIN node ON reach.b = node.key GROUP BY reach.a HAVING bool_or(node.verdict = 'block') AND NOT bool_or(node.verdict = 'allow')),
p AS (SELECT page_id, row_number() OVER () AS rid, {_host('url')} AS host, {_path('url')} AS path, {_key('url')} AS key FROM pages),
hit AS (SELECT n.rid, arg_max(r.rh || r.rp, length(r.rh || r.rp) * 2 + (r.verdict = 'allow')::INT) AS rule, arg_max(r.verdict, length(r.rh || r.rp) * 2 + (r.verdict = 'allow')::INT) AS verdict FROM p n JOIN rules r ON {_FIT} GROUP BY n.rid)
SELECT p.page_id, p.host, p.path, hit.rule, coalesce(hit.verdict, CASE WHEN spread.key IS NOT NULL THEN 'block' ELSE 'allow' END) AS verdict FROM p LEFT JOIN hit ON p.rid = hit.rid LEFT JOIN spread ON p.key = spread.key"""

ORACLES: dict[str, str] = {"op2_redirect_equivalence": URL_RULES}
