"""DuckDB SQL for the training-data queries that SQL can express."""

from __future__ import annotations

from rasterruns.llm import chat_windows as chat


def _reach(links: str, nodes: str) -> str:
    """CTEs: every node's smallest reachable id."""
    return f"reach(a, b) AS (SELECT id, id FROM {nodes} UNION SELECT r.a, l.v FROM reach r JOIN {links} l ON l.u = r.b), comp AS (SELECT a AS id, min(b) AS component_id FROM reach GROUP BY a)"


OP2 = rf"""WITH RECURSIVE w AS (SELECT doc_id AS id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT id, CASE WHEN len(w) < 3 THEN array_to_string(w, ' ') ELSE array_to_string(w[i:i + 2], ' ') END AS g FROM (SELECT id, w, unnest(range(1, greatest(len(w) - 1, 2))) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT id, count(*) AS n FROM s GROUP BY id),
c AS (SELECT a.id AS u, b.id AS v, count(*) AS k FROM s a JOIN s b USING (g) WHERE a.id <> b.id GROUP BY ALL),
l AS (SELECT u, v FROM c JOIN n x ON x.id = u JOIN n y ON y.id = v WHERE 100 * k >= 85 * (x.n + y.n - k)),
{_reach('l', 'w')}
SELECT w.id AS doc_id, coalesce(n, 0) AS n_shingles, component_id, w.id = component_id AS kept FROM w LEFT JOIN n USING (id) JOIN comp USING (id)"""

OP3 = f"""WITH RECURSIVE w AS (SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings),
g AS (SELECT *, sqrt(list_inner_product(v, v)) AS m FROM w WHERE v IS NOT NULL AND len(list_filter(v, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_inner_product(v, v) > 0),
l AS (SELECT a.id AS u, b.id AS v FROM g a JOIN g b ON a.id <> b.id AND len(a.v) = len(b.v) WHERE list_inner_product(a.v, b.v) / (a.m * b.m) >= 0.9),
{_reach('l', 'w')}
SELECT w.id AS vec_id, (SELECT count(*) FROM l WHERE u = w.id) AS n_links, component_id, w.id = component_id AS kept FROM w JOIN comp USING (id)"""

OP4 = """WITH q AS (SELECT vec_id, list_transform(embedding::DOUBLE[], lambda x: floor(256 * x)) AS v FROM embeddings),
s AS (SELECT a.vec_id AS query_id, b.vec_id, CAST(list_inner_product(a.v, b.v) AS BIGINT) AS score FROM q a JOIN q b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
SELECT * FROM r WHERE rank <= 5"""


def _escaped(text: str) -> str:
    for plain, safe in chat.ESCAPES:
        text = f"replace({text}, '{plain}', '{safe}')"
    return text


_PIECE = len(chat.OPEN_NEW) + len(chat.CLOSE) + 1
_LEADS = ", ".join(f"lead(win, {k}) OVER l AS w{k}, lead(start, {k}) OVER l AS s{k}" for k in range(1, chat.HISTORY_TURNS + 1))
_REPEATS = " + ".join(f"(coalesce(w{k} > {f'greatest(win, w{k - 1})' if k > 1 else 'win'} AND s{k} - start <= {chat.HISTORY_TOKENS}, false))::BIGINT" for k in range(1, chat.HISTORY_TURNS + 1))
OP6 = f"""WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
a AS (SELECT *, row_number() OVER l AS pos, replace({_escaped('role')}, chr(10), '&n') AS safe_role, {_escaped('text')} AS safe FROM t WINDOW l AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)),
b AS (SELECT *, pos = 1 AND role = 'system' AS sys, CASE WHEN pos = 1 AND role = 'system' THEN 0 ELSE (length(safe) + 3) // 4 + 4 END AS tokens FROM a),
c AS (SELECT *, coalesce(sum(tokens) OVER (PARTITION BY conv_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM b),
d AS (SELECT *, start // {chat.BUDGET // 2} AS span FROM c),
e AS (SELECT *, (span IS DISTINCT FROM lag(span) OVER (PARTITION BY conv_id ORDER BY pos))::BIGINT AS opens FROM d),
f AS (SELECT *, sum(opens) OVER (PARTITION BY conv_id ORDER BY pos ROWS UNBOUNDED PRECEDING)::BIGINT AS win FROM e),
g AS (SELECT *, max(win) OVER (PARTITION BY conv_id) AS last_win, {_LEADS} FROM f WINDOW l AS (PARTITION BY conv_id ORDER BY pos)),
h AS (SELECT *, 1 + CASE WHEN sys THEN last_win - 1 ELSE {_REPEATS} END AS times FROM g)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY pos)) AS turns_sha256,
 CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars, sha256(coalesce(string_agg(text, '' ORDER BY pos) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
 CAST(sum(times * (length(safe_role) + length(safe) + {_PIECE})) AS BIGINT) AS formatted_chars, max(last_win) AS n_windows FROM h GROUP BY conv_id"""
