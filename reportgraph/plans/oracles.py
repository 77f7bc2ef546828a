"""The mining chain as SQL of another engine, step by step, for checking results."""

from __future__ import annotations

from reportgraph.functions.text import TYPES, value_type_sql
from reportgraph.operators.labeling import DETERMINERS
from reportgraph.sources.corpus import SENTENCES_SQL

_EDGE = ", ".join(f"'{d}'" for d in DETERMINERS)
_ORDER = "[" + ", ".join(f"'{t}'" for t in TYPES) + "]"

STEPS = {
    "candidates": """SELECT report_id, sent_no, trim(split_part(text, chr(9), 1)) AS name, trim(split_part(text, chr(9), 2)) AS value, 'table' AS pattern FROM sentences WHERE contains(text, chr(9))
 UNION ALL SELECT report_id, sent_no, trim(substr(text, 1, position(':' IN text) - 1)) AS name, trim(substr(text, position(':' IN text) + 1)) AS value, 'key_value' AS pattern
 FROM sentences WHERE contains(text, ':') AND NOT contains(text, chr(9)) AND trim(substr(text, position(':' IN text) + 1)) <> ''""",
    "clean": r"SELECT report_id, sent_no, lower(trim(regexp_replace(name, '([a-z])([A-Z])', '\1 \2', 'g'))) AS name, value, pattern FROM candidates WHERE regexp_full_match(name, '[\p{L} ]+')",
    "names": "SELECT name, count(*) AS c, string_split(name, ' ') AS words FROM clean GROUP BY name",
    "grams": f"""SELECT * FROM (SELECT name, c, array_to_string(words[i:i + n - 1], ' ') AS gram, words[i] AS head, words[i + n - 1] AS tail, n, i AS place
 FROM names, unnest(range(1, 4)) AS t(n), unnest(range(1, len(words) - n + 2)) AS u(i)) WHERE head NOT IN ({_EDGE}) AND tail NOT IN ({_EDGE})""",
    "counts": "SELECT gram, n, sum(c)::BIGINT AS freq FROM grams GROUP BY gram, n",
    "top": "SELECT * FROM counts ORDER BY freq DESC, n DESC, gram LIMIT 100",
    "types": """SELECT gram, n, freq, row_number() OVER (ORDER BY freq DESC, n DESC, gram) AS rank FROM top a WHERE NOT EXISTS
 (SELECT 1 FROM top b WHERE a.n < b.n AND a.freq = b.freq AND contains(' ' || b.gram || ' ', ' ' || a.gram || ' '))""",
    "resolved": "SELECT name, arg_min(gram, (-g.n, -t.freq, -place, gram)) AS entity FROM grams g JOIN types t USING (gram) GROUP BY name",
    "seeds": "SELECT report_id, sent_no, entity, value FROM clean JOIN resolved USING (name)",
    "vcounts": f"SELECT entity, {value_type_sql('value')} AS value_type, count(*) AS c FROM seeds GROUP BY ALL",
    "vtypes": f"SELECT entity, arg_min(value_type, (-c, list_position({_ORDER}, value_type))) AS value_type, max(c) AS support, sum(c)::BIGINT AS freq FROM vcounts GROUP BY entity",
    "described": "SELECT entity FROM seeds GROUP BY entity HAVING quantile_disc(len(string_split(value, ' ')), 0.5) > 5",
    "dcounts": """SELECT value, entity, count(*) AS c FROM seeds WHERE entity IN (SELECT entity FROM vtypes WHERE value_type <> 'Boolean') AND entity NOT IN (SELECT entity FROM described)
 AND len(string_split(value, ' ')) <= 5 AND length(value) >= 3 AND lower(value) NOT IN ('true', 'false') GROUP BY value, entity""",
    "dictionary": "SELECT value, len(string_split(value, ' ')) AS tokens, arg_min(entity, (-c, entity)) AS entity, max(c) AS support FROM dcounts GROUP BY value",
    "free": "SELECT s.report_id, s.sent_no, string_split(text, ' ') AS w FROM sentences s ANTI JOIN seeds d ON s.report_id = d.report_id AND s.sent_no = d.sent_no",
    "spans": r"""SELECT report_id, sent_no, b AS "begin", n AS size, regexp_replace(array_to_string(w[b + 1:b + n], ' '), '[,.;!?]+$', '') AS value
 FROM free, unnest(range(1, 6)) AS t(n), unnest(range(0, len(w) - n + 1)) AS u(b)""",
    "propagated": 'SELECT report_id, sent_no, "begin", size, entity, value FROM spans JOIN dictionary USING (value)',
    "mentions": "SELECT report_id, sent_no, entity, value FROM seeds UNION ALL SELECT report_id, sent_no, entity, value FROM propagated",
    "freqs": "SELECT entity, count(*) AS f FROM mentions GROUP BY entity",
    "present": "SELECT DISTINCT report_id, sent_no, entity FROM mentions",
    "joint": "SELECT a.entity AS e1, b.entity AS e2, count(*) AS f_joint FROM present a JOIN present b ON a.report_id = b.report_id AND a.sent_no = b.sent_no AND a.entity < b.entity GROUP BY ALL",
    "scored": """SELECT e1, e2, f_joint, x.f AS f1, y.f AS f2, total, ln(f_joint * total::DOUBLE / (x.f::DOUBLE * y.f)) AS pmi, ln(f_joint * total::DOUBLE / (x.f::DOUBLE * y.f)) / -ln(f_joint / total::DOUBLE) AS npmi
 FROM joint JOIN freqs x ON e1 = x.entity JOIN freqs y ON e2 = y.entity, (SELECT sum(f)::BIGINT AS total FROM freqs)""",
    "edges": "SELECT e1 AS src, e2 AS dst, npmi AS weight FROM scored WHERE npmi >= 0",
    "two_way": "SELECT src, dst, weight FROM edges UNION ALL SELECT dst, src, weight FROM edges",
}


def chain(select: str, *more: str) -> str:
    """``select`` over all steps (those not used are not run); ``more`` are further steps."""
    steps = [SENTENCES_SQL, *(f"{k} AS ({v})" for k, v in STEPS.items()), *more]
    return f"WITH RECURSIVE {', '.join(steps)} {select}"
