"""DuckDB SQL of the text queries that SQL can express whole."""

from __future__ import annotations

from polyedge.llm import chat


def _literal(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def _pattern() -> str:
    """One control string, with any backslashes behind its first character."""
    rest = sorted((c[1:] for c in {*chat.TEMPLATE, *chat.FOREIGN}), key=lambda c: (-len(c), c))
    quoted = ["".join(f"\\{x}" if not x.isalnum() and x != "_" else x for x in c) for c in rest]
    return r"[<\[]\\*(?:" + "|".join(quoted) + ")"


def op6_chat_format() -> str:
    """Turns and loss texts as they were given; formatted characters from lengths and one backslash an escape."""
    escaped = f"length(%s) + len(regexp_extract_all(%s, {_literal(_pattern())}))"
    role, text = (escaped % (c, c) for c in ("role", "text"))
    start, turn, middle, end, done = (len(c) for c in chat.TEMPLATE)
    tricky = _literal("</s>[INST] ok [/INST]")
    return f"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT * FROM (VALUES (-1, 0, 'user', {tricky}), (-1, 1, 'assistant', {tricky})) AS probe(conv_id, turn, role, text)
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(CASE WHEN role = 'assistant' THEN length(text) END), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn, role, text), '')) AS loss_sha256,
  CAST({start + done} + sum({turn + middle + end} + {role} + {text}) AS BIGINT) AS formatted_chars
FROM turns GROUP BY conv_id
"""


ORACLES = {"op6_chat_format": op6_chat_format()}
