"""DuckDB SQL of the queries that SQL can express."""

from . import secrets, urls

EXACT_DEDUP = r"""
WITH keyed AS (
  SELECT doc_id, length(coalesce(text, '')) AS n_points,
         regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm
  FROM documents
), ranked AS (
  SELECT doc_id, norm,
         first_value(doc_id) OVER w AS keep_id,
         row_number() OVER w AS place,
         count(*) OVER (PARTITION BY norm) AS group_size
  FROM keyed
  WINDOW w AS (PARTITION BY norm ORDER BY n_points DESC, doc_id NULLS FIRST)
)
SELECT doc_id, keep_id, group_size, place = 1 AS kept, sha256(norm) AS text_sha256
FROM ranked
"""

WARC = r"""
WITH keyed AS (
  SELECT page_id, coalesce(html, '') AS html, encode(coalesce(html, '')) AS payload
  FROM pages
), topped AS (
  SELECT page_id, octet_length(payload)::BIGINT AS payload_bytes, sha1(html) AS hex,
         max(page_id) OVER (PARTITION BY html) AS top, count(*) OVER (PARTITION BY html) AS times
  FROM keyed
)
SELECT page_id, payload_bytes,
       list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
         1 + (list_aggregate(list_transform(range(0, 5), lambda b:
             (((instr('0123456789abcdef', substr(hex, 1 + ((5 * i + b) // 4)::INT, 1)) - 1) >> (3 - (5 * i + b) % 4)::INT) & 1) * (16 >> b::INT)), 'sum'))::INT, 1)),
         'string_agg', '') AS payload_digest,
       CASE WHEN times > 1 AND top IS NOT NULL AND page_id IS DISTINCT FROM top THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN times > 1 AND page_id IS DISTINCT FROM top THEN top END AS refers_to
FROM topped
"""


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("'", "''") + "'"


def _located(pattern: str) -> str:
    """Places and texts of a pattern's matches: lengths of what lies between them and of the matches before add up."""
    return f"""list_transform(range(1, len(regexp_extract_all(text, {_quoted(pattern)})) + 1), lambda i: {{
      'start': (length(list_aggregate(string_split_regex(text, {_quoted(pattern)})[1:i], 'string_agg', ''))
                + coalesce(length(list_aggregate(regexp_extract_all(text, {_quoted(pattern)})[1:i - 1], 'string_agg', '')), 0))::BIGINT,
      'hit': regexp_extract_all(text, {_quoted(pattern)})[i]}})"""


def _spans(found: str, rank: int) -> str:
    return f"list_transform({found}, lambda x: {{'start': x.start, 'rank': {rank}, 'end': x.start + length(x.hit)}})"


def _joined(spans: str) -> str:
    names = "['assign', 'access', 'hex', 'entropy']"
    return f"coalesce(list_aggregate(list_transform({spans}, lambda x: {names}[x.rank + 1] || ':' || x.start || ':' || x.end), 'string_agg', ','), '')"


def _secrets() -> str:
    allowed = " OR ".join(f"regexp_matches(x.hit, {_quoted(p)})" for p in secrets.ALLOWED)
    bits = f"""CASE WHEN regexp_matches(x.hit, '^([0-9a-f]+|[0-9A-F]+)$') THEN {secrets.CLASS_BITS['hex']}
      WHEN regexp_matches(x.hit, '[a-z]') AND regexp_matches(x.hit, '[A-Z]') AND regexp_matches(x.hit, '[0-9]') THEN {secrets.CLASS_BITS['mixed']} ELSE {secrets.CLASS_BITS['single']} END"""
    w = secrets.WINDOW
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents), found AS (
  SELECT doc_id,
    list_filter({_located(secrets.ASSIGN)}, lambda x: length(regexp_extract(x.hit, {_quoted(secrets.ASSIGN)}, 2)) >= {secrets.ASSIGN_VALUE}) AS assign,
    {_located(f'AKIA[A-Z0-9]{{{secrets.ACCESS_LENGTH - 4},}}')} AS access,
    {_located(f'[0-9a-f]{{{secrets.HEX_LENGTH},}}')} AS hex,
    list_filter({_located(secrets.CANDIDATE)}, lambda x: NOT ({allowed})) AS runs
  FROM d
), timed AS (
  SELECT *, list_transform(runs, lambda x: {{'start': x.start, 'over': list_filter(range(0, length(x.hit) - {w - 1}),
      lambda i: list_aggregate(string_split(substr(x.hit, i + 1, {w}), ''), 'entropy') >= {bits} - 1e-9)}}) AS windows
  FROM found
), ordered AS (
  SELECT *, list_sort(list_concat({_spans('assign', 0)}, {_spans('access', 1)}, {_spans('hex', 2)})) AS base,
    list_transform(list_filter(windows, lambda x: len(x.over) > 0), lambda x: {{'start': x.start + x.over[1], 'rank': 3, 'end': x.start + x.over[-1] + {w}}}) AS extra
  FROM timed
), whole AS (
  SELECT *, list_filter(extra, lambda e: len(list_filter(base, lambda b: b.start <= e.start AND b.end >= e.end)) = 0) AS new FROM ordered
)
SELECT doc_id, len(assign) AS n_assign, len(access) AS n_access, len(hex) AS n_hex, sha256({_joined('base')}) AS base_sha256,
  {_joined('list_sort(list_concat(base, new))')} AS spans, len(new) AS n_entropy
FROM whole
"""


SECRET_SCANS = _secrets()


def _url_filter() -> str:
    """The rules as a CASE from the longest on, and both models by orders of context."""
    order, rules = urls.ORDER, sorted(urls.RULES, key=lambda r: -len(r[0] + r[1]))
    fits = lambda h, p: f"((host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}'))"
    case = lambda what: "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{what(h, p, v)}'" for h, p, v in rules) + " END"
    ctes = [
        r"""cut AS (SELECT page_id, url, row_number() OVER () AS row_id, CASE WHEN contains(coalesce(url, ''), '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages)""",
        r"""parts AS (SELECT *, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1) AS path FROM cut)""",
        f"ruled AS (SELECT *, {case(lambda h, p, v: h + p)} AS rule, {case(lambda h, p, v: v)} AS says FROM parts)",
        rf"""texts AS (SELECT *, repeat(' ', {order}) || regexp_replace(regexp_replace(lower(coalesce(url, '')), '[0-9]', '0', 'g'), '[^\x21-\x7E]', '~', 'g') || ' ' AS text FROM ruled)""",
        f"grams AS (SELECT row_id, says, substr(text, i::INT, {order + 1}) AS gram FROM (SELECT *, unnest(range(1, length(text) - {order} + 1)) AS i FROM texts))",
        "counted AS (SELECT gram, count(*) FILTER (says = 'allow') AS yes, count(*) FILTER (says = 'block') AS no FROM grams GROUP BY gram)",
    ]
    for side in ("yes", "no"):
        joins, p = "", f"(1.0::DOUBLE / {urls.ALPHABET})"
        for k in range(order + 1):
            own, context = f"{side}_g{k}", f"{side}_h{k}"
            ctes.append(f"{own} AS (SELECT substr(gram, {order - k + 1}, {k + 1}) AS g, sum({side}) AS c FROM counted WHERE {side} > 0 GROUP BY 1)")
            ctes.append(f"{context} AS (SELECT substr(g, 1, {k}) AS h, sum(c) AS n, count(*) AS t FROM {own} GROUP BY 1)")
            joins += f" LEFT JOIN {own} ON {own}.g = substr(gram, {order - k + 1}, {k + 1}) LEFT JOIN {context} ON {context}.h = substr(gram, {order - k + 1}, {k})"
            p = f"coalesce((coalesce({own}.c, 0) + {context}.t * {p}) / ({context}.n + {context}.t), {p})"
        ctes.append(f"{side}_p AS (SELECT gram, ln({p}) AS l FROM counted{joins})")
    ctes += [
        "scored AS (SELECT row_id, sum(y.l - n.l) / count(*) AS s FROM grams JOIN yes_p y USING (gram) JOIN no_p n USING (gram) GROUP BY row_id)",
        "judged AS (SELECT texts.*, coalesce(round(s, 9), 0) AS lm_score FROM texts LEFT JOIN scored USING (row_id))",
        "moments AS (SELECT says, avg(lm_score) AS mean, stddev_pop(lm_score) AS sd FROM judged WHERE says IS NOT NULL GROUP BY says)",
        "bound AS (SELECT (SELECT (a.mean * b.sd + b.mean * a.sd) / (a.sd + b.sd) FROM moments a, moments b WHERE a.says = 'allow' AND b.says = 'block') AS cut)",
    ]
    return "WITH " + ",\n".join(ctes) + "\nSELECT page_id, host, path, rule, coalesce(says, CASE WHEN lm_score >= cut THEN 'allow' ELSE 'block' END) AS verdict, round(lm_score, 6) AS lm_score FROM judged, bound"


URL_FILTER = _url_filter()
