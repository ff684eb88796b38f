"""DuckDB SQL for the queries that SQL can express."""

from __future__ import annotations

OP2 = r"""
WITH d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents),
g AS (SELECT t, min(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
SELECT d.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256
FROM d JOIN g ON d.t = g.t
"""

OP7 = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
e AS (SELECT *, length(role) + length(regexp_replace(text, '([<\[])(\\*)(/?s>|/?INST\])', '\1\\\2\3', 'g')) + 18 AS n,
        count(*) OVER (PARTITION BY conv_id) AS turns, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS i FROM c),
p AS (SELECT *, sum(n) OVER (PARTITION BY conv_id ORDER BY i) AS upto FROM e)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY i)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY i) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(upto) FILTER (role = 'assistant' OR i = turns) AS BIGINT) AS formatted_chars
FROM p GROUP BY conv_id
"""


WORDS = r"""string_split_regex(trim(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), '[\x20\x09-\x0D]+')"""

OP1 = f"""
WITH RECURSIVE docs AS (SELECT doc_id, {WORDS} AS w FROM documents),
g AS (SELECT DISTINCT doc_id, array_to_string(w[i + 1 : i + least(len(w), 5)], ' ') AS g
      FROM (SELECT doc_id, w, unnest(range(0, len(w) - least(len(w), 5) + 1)) AS i FROM docs WHERE w <> ['']) x),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM g x JOIN g y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY x.doc_id, y.doc_id),
l AS (SELECT a, b FROM p JOIN n s ON p.a = s.doc_id JOIN n t ON p.b = t.doc_id WHERE 100 * c >= 75 * (s.n + t.n - c)),
r AS (SELECT doc_id, doc_id AS reach FROM documents UNION SELECT r.doc_id, l.b FROM r JOIN l ON r.reach = l.a),
m AS (SELECT doc_id, min(reach) AS component_id FROM r GROUP BY doc_id)
SELECT m.doc_id, coalesce(n.n, 0) AS n_shingles, m.component_id FROM m LEFT JOIN n ON m.doc_id = n.doc_id
"""

OP6 = f"""
WITH items AS (SELECT item_id, {WORDS} AS w FROM benchmark), docs AS (SELECT doc_id, {WORDS} AS w FROM documents),
q AS (SELECT DISTINCT item_id, least(len(w), 5) AS width, array_to_string(w[i + 1 : i + least(len(w), 5)], ' ') AS g
      FROM (SELECT item_id, w, unnest(range(0, len(w) - least(len(w), 5) + 1)) AS i FROM items WHERE w <> ['']) x),
n AS (SELECT item_id, count(*) AS item_shingles FROM q GROUP BY item_id),
d AS (SELECT DISTINCT doc_id, 5 AS width, array_to_string(w[i + 1 : i + 5], ' ') AS g
      FROM (SELECT doc_id, w, unnest(range(0, len(w) - 4)) AS i FROM docs WHERE len(w) >= 5) x),
m AS (SELECT doc_id, q.item_id, count(*) AS common FROM d JOIN q ON d.width = q.width AND d.g = q.g GROUP BY doc_id, q.item_id)
SELECT m.doc_id, m.item_id, n.item_shingles, m.common, m.common / n.item_shingles AS containment
FROM m JOIN n ON m.item_id = n.item_id WHERE m.common * 100 >= n.item_shingles * 75
"""


def _op3() -> str:
    """The rules as SQL: the run of each rule is looked for and taken out of what is left, one after the other."""
    from .license_scan import RULES, known_sentences

    known = " UNION ALL ".join(f"SELECT '{s}' AS s, '{name}' AS id" for s, name in known_sentences().items())
    steps, names = [], []
    for k, (name, run) in enumerate(RULES):
        piece = "".join(f"|{x}|" for x in run)
        steps.append(f"r{k + 1} AS (SELECT * EXCLUDE (rest), CASE WHEN contains(rest, '{piece}') THEN '{name}' END AS l{k}, replace(rest, '{piece}', '||.||') AS rest FROM r{k})")
        names.append(f"l{k}")
    firsts = []
    for k, (name, _) in enumerate(RULES):  # a name only where no rule before has given it
        before = [f"l{j} IS NULL" for j in range(k) if RULES[j][0] == name]
        firsts.append(f"CASE WHEN {' AND '.join([*before, 'true'])} THEN l{k} END")
    return rf"""
WITH known AS ({known}),
parts AS (SELECT doc_id, unnest(string_split_regex(lower(coalesce(text, '')), '[.!?][\x20\x09-\x0D]+|\n')) AS s,
            generate_subscripts(string_split_regex(lower(coalesce(text, '')), '[.!?][\x20\x09-\x0D]+|\n'), 1) AS i FROM documents),
hits AS (SELECT doc_id, i, id FROM (SELECT doc_id, i, trim(regexp_replace(s, '[^a-z0-9]+', ' ', 'g')) AS s FROM parts) p JOIN known ON p.s = known.s),
r0 AS (SELECT doc_id, count(*) AS n_sentences, string_agg(id, '|' ORDER BY i) AS sentence_ids, '|' || string_agg(id, '||' ORDER BY i) || '|' AS rest FROM hits GROUP BY doc_id),
{", ".join(steps)}
SELECT doc_id, n_sentences, sentence_ids, concat_ws('|', {", ".join(firsts)}) AS licenses FROM r{len(RULES)}
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_jaccard_join": OP1, "op2_exact_dedup": OP2, "op3_license_scan": _op3(), "op6_decontamination": OP6, "op7_chat_format": OP7}
