"""DuckDB SQL for the queries of the training-data operators that SQL can express."""

from __future__ import annotations

import math
import re

from . import secrets

OP1 = """
WITH p AS (
  SELECT page_id, encode(coalesce(html, '')) AS body FROM pages
), d AS (
  SELECT page_id, octet_length(body)::BIGINT AS payload_bytes, lower(sha256(body)) AS payload_digest FROM p
), f AS (
  SELECT payload_digest, min(page_id) AS first_id FROM d WHERE payload_bytes >= 100 GROUP BY payload_digest
)
SELECT d.page_id, d.payload_bytes, d.payload_digest,
       CASE WHEN f.first_id <> d.page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN f.first_id <> d.page_id THEN f.first_id END AS refers_to
FROM d LEFT JOIN f USING (payload_digest)
"""

OP8 = """
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents
), k AS (
  SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM l
), often AS (
  SELECT key FROM k WHERE key <> '' GROUP BY key HAVING count(DISTINCT doc_id) >= 10
), m AS (
  SELECT k.*, o.key IS NOT NULL AS goes FROM k LEFT JOIN often o ON k.key = o.key
)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (WHERE goes))::BIGINT AS n_dropped,
       lower(sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT goes), ''))) AS kept_sha256
FROM m GROUP BY doc_id
"""


def _sql(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def _spans(pattern: str, group: int, least: int) -> str:
    """List of (s, e, v) of matches in t: lengths of the parts between matches and of matches before add up to s."""
    parts, matches, values = f"string_split_regex(t, {_sql(pattern)})", f"regexp_extract_all(t, {_sql(pattern)}, 0)", f"regexp_extract_all(t, {_sql(pattern)}, {group})"
    before = "coalesce(list_sum([length(x) for x in parts[1:i]]), 0) + coalesce(list_sum([length(x) for x in matches[1:i-1]]), 0)"
    return f"""(SELECT coalesce(list({{'s': ({before})::BIGINT, 'e': ({before} + length(matches[i]))::BIGINT, 'v': matches[i]}} ORDER BY i)
         FILTER (WHERE length(vals[i]) >= {least}), [])
       FROM (SELECT unnest(range(1, len(matches) + 1)) AS i, parts, matches, vals
             FROM (SELECT {parts} AS parts, {matches} AS matches, {values} AS vals)))"""


def op2_sql() -> str:
    kinds = [(k, _spans(p, g, n), "true") for k, p, g, n in secrets.BASE]
    for c in secrets.CLASSES:
        table = "[" + ", ".join(str(round(n * math.log2(n) * secrets.SCALE) if n else 0) for n in range(c.window + 1)) + "]"
        window = f"v[j:j + {c.window - 1}]"
        total = f"list_sum([{table}[length(w) - length(replace(w, c, '')) + 1] for c in list_distinct(string_split(w, ''))])"
        # DuckDB's expressions never recurse, so they need no possessive repetitions
        runs = [re.sub(r"(?<=[\])])([*+])\+", r"\1", p) for p in secrets.ALLOWED_RUNS]
        first = "arg_min(w, total * 100000000 + j)"
        free = " AND ".join(f"NOT regexp_matches({first}, {_sql(p)})" for p in secrets.ALLOWED_WINDOWS)
        best = f"(SELECT min(total) <= {c.max_sum} AND {free} FROM (SELECT w, j, {total} AS total FROM (SELECT {window} AS w, j FROM (SELECT unnest(range(1, length(v) - {c.window - 2})) AS j))))"
        tests = [f"regexp_matches(v, {_sql(p)})" for p in c.need] + [f"NOT regexp_matches(v, {_sql(p)})" for p in runs]
        kinds.append((c.kind, _spans(f"[{c.chars}]{{{c.window},}}", 0, c.window), " AND ".join(tests) + f" AND {best}"))
    rows = "\nUNION ALL\n".join(f"SELECT doc_id, {i} AS o, '{k}' AS kind, x.s AS s, x.e AS e, x.v AS v FROM (SELECT doc_id, unnest({spans}) AS x FROM d)" for i, (k, spans, _) in enumerate(kinds))
    judged = "\nUNION ALL\n".join(f"SELECT doc_id, o, kind, s, e FROM r WHERE o = {i} AND {test}" for i, (_, _, test) in enumerate(kinds))
    name = "kind || ':' || s || ':' || e"
    counts = ", ".join(f"(count(j.kind) FILTER (WHERE j.kind = '{k}'))::BIGINT AS n_{k}" for k, *_ in kinds[:3])
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
r AS ({rows}),
j AS ({judged})
SELECT d.doc_id, {counts},
       lower(sha256(coalesce(string_agg({name}, ',' ORDER BY s, o, e) FILTER (WHERE o < 3), ''))) AS base_sha256,
       coalesce(string_agg({name}, ',' ORDER BY s, o, e) FILTER (WHERE o IS NOT NULL), '') AS spans
FROM d LEFT JOIN j USING (doc_id) GROUP BY d.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_warc_archives": OP1, "op2_secret_spans": op2_sql(), "op8_line_dedup": OP8}
