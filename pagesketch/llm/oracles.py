"""DuckDB SQL for the operators that SQL can express."""

from __future__ import annotations

from pagesketch.llm import license_scan, mixing, url_filter

UPPER, LOWER = url_filter.UPPER, url_filter.LOWER
BLANKS = r"[\x20\x09-\x0D]+"
WORDS = r"[^\x20\x09-\x0D]+"

OP8 = f"""
WITH n AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '{BLANKS}', ' ', 'g')) AS text_sha256 FROM documents),
g AS (SELECT text_sha256, min(doc_id) AS keep_id, count(*)::BIGINT AS group_size FROM n GROUP BY 1)
SELECT doc_id, keep_id, group_size, coalesce(doc_id = keep_id, FALSE) AS kept, text_sha256 FROM n JOIN g USING (text_sha256)"""


def _rules(host: str, path: str, what: str) -> str:
    """CASE over the rules, the longest first."""
    out = []
    for r in sorted(url_filter.RULES, key=lambda r: (-len(r.text), r.text)):
        out.append(f"WHEN ({host} = '{r.host}' OR ends_with({host}, '.{r.host}')) AND starts_with({path}, '{r.path}') THEN '{r.text if what == 'text' else r.verdict}'")
    return f"CASE {' '.join(out)} END"


def _rest(url: str) -> str:
    return f"CASE WHEN contains({url}, '://') THEN substr({url}, instr({url}, '://') + 3) ELSE '' END"


def _parts(rest: str) -> tuple[str, str, str]:
    host = f"translate(regexp_extract({rest}, '^([^/?#]*)', 1), '{UPPER}', '{LOWER}')"
    return host, f"regexp_extract({rest}, '^[^/?#]*([^?#]*)', 1)", f"regexp_extract({rest}, '^[^/?#]*([^#]*)', 1)"


_host, _path, _tail = _parts("rest")
_thost, _, _ttail = _parts("target")
OP9 = f"""
WITH RECURSIVE p AS (SELECT page_id, html, coalesce({_rest('url')}, '') AS rest FROM pages),
q AS (SELECT page_id, html, {_host} AS host, {_path} AS path, {_tail} AS tail FROM p),
r AS (SELECT page_id, html, host, path, CASE WHEN host <> '' THEN host || tail END AS node, {_rules('host', 'path', 'text')} AS rule, {_rules('host', 'path', 'verdict')} AS own FROM q),
t AS (SELECT node AS src, coalesce({_rest('link')}, '') AS target FROM (SELECT node, unnest([
  regexp_extract(regexp_extract(html, '(?is)<link\\b[^>]*\\brel\\s*=\\s*["'']?canonical\\b[^>]*>'), '(?is)\\bhref\\s*=\\s*["'']?([^"''\\s>]+)', 1),
  regexp_extract(regexp_extract(html, '(?is)<meta\\b[^>]*\\bhttp-equiv\\s*=\\s*["'']?refresh\\b[^>]*>'), '(?is)\\burl\\s*=\\s*["'']?([^"''\\s>;]+)', 1)]) AS link FROM r WHERE html IS NOT NULL)),
e AS (SELECT src, dst FROM (SELECT src, {_thost} || {_ttail} AS dst, {_thost} AS h FROM t) WHERE src IS NOT NULL AND h <> '' AND src <> dst),
b AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e),
reach(node, other) AS (SELECT src, src FROM b UNION SELECT reach.node, b.dst FROM reach JOIN b ON reach.other = b.src),
v AS (SELECT node, {_rules("regexp_extract(other, '^([^/?#]*)', 1)", "regexp_extract(other, '^[^/?#]*([^?#]*)', 1)", 'verdict')} AS v FROM reach),
a AS (SELECT node, CASE WHEN bool_or(v = 'allow') THEN 'allow' WHEN bool_or(v = 'block') THEN 'block' END AS alias_verdict FROM v GROUP BY 1)
SELECT page_id, host, path, rule, coalesce(own, alias_verdict, 'allow') AS verdict FROM r LEFT JOIN a USING (node)"""

OP3 = f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{WORDS}') AS w FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) END) AS s FROM w),
x AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM s),
e AS (SELECT a.doc_id AS src, b.doc_id AS dst FROM x a JOIN x b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
both_ways AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e),
reach(doc_id, other) AS (SELECT doc_id, doc_id FROM s UNION SELECT reach.doc_id, dst FROM reach JOIN both_ways ON other = src)
SELECT doc_id, len(s)::BIGINT AS n_shingles, component_id, doc_id = component_id AS kept FROM s JOIN (SELECT doc_id, min(other) AS component_id FROM reach GROUP BY 1) USING (doc_id)"""


def _op1() -> str:
    idf, other, vectors = license_scan.weights(license_scan.TEMPLATES)
    cells = ", ".join(f"('{k}', {i}, '{t}', {w!r}::DOUBLE)" for (k, i), v in vectors.items() for t, w in v.items())
    known = ", ".join(f"('{t}', {w!r}::DOUBLE)" for t, w in idf.items())
    names = ", ".join(f"('{k.lower()}', '{k}')" for k in sorted(license_scan.TEMPLATES))
    anchors = " OR ".join(f"contains(lower(x), '{a}')" for a in license_scan.ANCHORS)
    return f"""
WITH f AS (SELECT doc_id, concat_ws('/', source, lang, doc_id::VARCHAR) AS path, text FROM documents),
a AS (SELECT doc_id, text, len(list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^ \\t\\n\\v\\f\\r]'))) AS n_lines, regexp_matches(regexp_extract(path, '([^/]*)$', 1), '{license_scan.LICENSE_FILE}') AS named
  FROM (SELECT doc_id, path, text, text AS x FROM f WHERE text IS NOT NULL) WHERE ({anchors}) OR named),
p AS (SELECT doc_id, n_lines, named, text, string_split_regex(text, '{license_scan.PARAGRAPH_END}') AS paragraphs FROM a),
x AS (SELECT doc_id, n_lines, unnest(string_split(text, chr(10)) || paragraphs) AS x FROM p
  UNION ALL SELECT doc_id, n_lines, unnest(string_split(regexp_replace(paragraph, '{license_scan.SENTENCE_END}', '\\1' || chr(1) || '\\2', 'g'), chr(1))) FROM (SELECT doc_id, n_lines, unnest(paragraphs) AS paragraph FROM p)),
y AS (SELECT doc_id, n_lines, x FROM x WHERE {anchors} UNION ALL SELECT doc_id, n_lines, text FROM p WHERE named),
u AS (SELECT DISTINCT doc_id, n_lines, trim(regexp_replace(lower(x), '{license_scan.TERM}', ' ', 'g')) AS unit FROM y),
w AS (SELECT doc_id, n_lines, unit, unnest(string_split(unit, ' ')) AS term FROM u),
tf AS (SELECT doc_id, n_lines, unit, term, count(*) * coalesce(idf, {other!r}::DOUBLE) AS weight FROM w LEFT JOIN (VALUES {known}) k(term, idf) USING (term) WHERE term <> '' GROUP BY doc_id, n_lines, unit, term, idf),
norms AS (SELECT doc_id, unit, sqrt(sum(weight * weight)) AS norm FROM tf GROUP BY 1, 2),
cosines AS (SELECT doc_id, n_lines, unit, license, notice, round(sum(weight * tw) / max(norm), 6) AS cosine FROM tf JOIN norms USING (doc_id, unit) JOIN (VALUES {cells}) c(license, notice, term, tw) USING (term) GROUP BY 1, 2, 3, 4, 5),
tags AS (SELECT doc_id, n_lines, regexp_replace(unnest(regexp_split_to_array(tag, '[ \\t()]+')), '(-only|-or-later|\\+)?\\.?$', '') AS identifier FROM (SELECT doc_id, n_lines, unnest(regexp_extract_all(lower(text), '{license_scan.SPDX}', 1)) AS tag FROM a)),
dots AS (SELECT doc_id, n_lines, license, cosine FROM cosines UNION ALL SELECT doc_id, n_lines, license, 1.0 FROM tags JOIN (VALUES {names}) s(identifier, license) USING (identifier)),
found AS (SELECT doc_id, license, cosine, n_lines FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY cosine DESC, license, n_lines) AS k FROM dots WHERE cosine >= {license_scan.MIN_COSINE}) WHERE k = 1),
own AS (SELECT f.doc_id, path, regexp_replace(path, '/?[^/]*$', '') AS dir, regexp_extract(path, '([^/]*)$', 1) AS name, license, cosine, n_lines FROM f LEFT JOIN found USING (doc_id)),
givers AS (SELECT dir AS giver, license AS given FROM (SELECT dir, license, row_number() OVER (PARTITION BY dir ORDER BY cosine DESC, name, license) AS k FROM own WHERE license IS NOT NULL AND (n_lines = 1 OR regexp_matches(name, '{license_scan.LICENSE_FILE}'))) WHERE k = 1),
near AS (SELECT dir, giver, given FROM (SELECT dir, giver, given, row_number() OVER (PARTITION BY dir ORDER BY length(giver) DESC) AS k FROM (SELECT DISTINCT dir FROM own) JOIN givers ON giver = '' OR dir = giver OR starts_with(dir, giver || '/')) WHERE k = 1)
SELECT doc_id, path, coalesce(license, given) AS license, CASE WHEN license IS NOT NULL THEN 'header' WHEN given IS NOT NULL THEN 'inherited' ELSE 'none' END AS found_by, cosine, CASE WHEN license IS NULL THEN giver END AS inherited_from
FROM own LEFT JOIN near USING (dir)"""


def _weights(level: str) -> str:
    named = mixing.WEIGHTS.get(level, {})
    return f"CASE {' '.join(f"WHEN {level} = '{k}' THEN {v}" for k, v in named.items())} ELSE {mixing.OTHER_WEIGHT} END::BIGINT" if named else f"{mixing.OTHER_WEIGHT}::BIGINT"


def _share(name: str, source: str, parent: str, child: str) -> str:
    """CTEs name_1 to name: the parent's total shared among children with cap and w."""
    of = f"PARTITION BY {parent}"
    order = f"{of} ORDER BY cap::DOUBLE / w, {child}"
    return f"""{name}_1 AS (SELECT *, sum(cap) OVER ({order}) - cap AS before, sum(w) OVER ({of}) - sum(w) OVER ({order}) + w AS weights FROM ({source})),
{name}_2 AS (SELECT *, cap::HUGEINT * weights <= (total - before)::HUGEINT * w AS is_full FROM {name}_1),
{name}_3 AS (SELECT *, total - sum(CASE WHEN is_full THEN cap ELSE 0 END) OVER ({of}) AS rest, sum(CASE WHEN is_full THEN 0 ELSE w END) OVER ({of}) AS rest_w FROM {name}_2),
{name}_4 AS (SELECT *, CASE WHEN is_full THEN cap ELSE (rest::HUGEINT * w // greatest(rest_w, 1))::BIGINT END AS part, row_number() OVER ({order}) AS place, count(*) OVER ({of}) AS n FROM {name}_3),
{name} AS (SELECT *, least(cap, part + CASE WHEN place = n AND NOT is_full THEN total - sum(part) OVER ({of}) ELSE 0 END)::BIGINT AS budget FROM {name}_4)"""


OP5 = f"""
WITH r AS (SELECT doc_id, coalesce(lang, '?') AS lang, coalesce(source, '?') AS source, len(regexp_extract_all(text, '{WORDS}'))::BIGINT AS n_tokens FROM documents),
rows_ AS (SELECT *, CASE WHEN regexp_extract(source, '([0-9])$', 1) IN ('0', '1', '2', '3', '4') THEN 'web' WHEN regexp_extract(source, '([0-9])$', 1) IN ('5', '6', '7') THEN 'reference' ELSE 'forum' END AS domain FROM r WHERE n_tokens > 0),
leaves AS (SELECT domain, lang, source, sum(n_tokens)::BIGINT AS leaf_tokens, (sum(n_tokens) * {mixing.MAX_EPOCHS})::BIGINT AS cap FROM rows_ GROUP BY 1, 2, 3),
{_share("top", f"SELECT 0 AS root, domain, sum(cap)::BIGINT AS cap, {_weights('domain')} AS w, (SELECT least(sum(cap), floor(sum(leaf_tokens) * {mixing.BUDGET_PERMILLE} / 1000.0))::BIGINT FROM leaves) AS total FROM leaves GROUP BY domain", "root", "domain")},
{_share("mid", f"SELECT domain, lang, sum(l.cap)::BIGINT AS cap, {_weights('lang')} AS w, max(budget) AS total FROM leaves l JOIN top USING (domain) GROUP BY domain, lang", "domain", "lang")},
{_share("low", f"SELECT domain, lang, source, leaf_tokens, l.cap, {_weights('source')} AS w, budget AS total FROM leaves l JOIN mid USING (domain, lang)", "domain, lang", "source")},
chosen AS (SELECT doc_id, domain, lang, source, n_tokens, budget // leaf_tokens AS whole, budget % leaf_tokens AS rest FROM rows_ JOIN low USING (domain, lang, source) WHERE budget > 0),
ep AS (SELECT *, unnest(range(1, whole + CASE WHEN rest > 0 THEN 2 ELSE 1 END)) AS epoch FROM chosen),
run AS (SELECT *, sum(n_tokens) OVER (PARTITION BY domain, lang, source, epoch ORDER BY md5('{mixing.SEED}:' || epoch || ':' || doc_id), doc_id ROWS UNBOUNDED PRECEDING) - n_tokens AS ahead FROM ep)
SELECT doc_id, domain, lang, source, epoch::INT AS epoch, n_tokens, (CASE WHEN epoch <= whole THEN n_tokens ELSE least(n_tokens, rest - ahead) END)::BIGINT AS taken_tokens FROM run WHERE epoch <= whole OR ahead < rest"""

SQL: dict[str, str] = {
    "op1_license_scan": _op1(),
    "op3_superminhash": OP3,
    "op5_mixing": OP5,
    "op8_exact_dedup": OP8,
    "op9_url_filters": OP9,
}
