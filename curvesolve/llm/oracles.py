"""DuckDB SQL for the corpus queries that SQL can express; the others are tested against brute force."""

#: Turns of the given tables hold no tool calls, so each stands alone.
CHAT = """
SELECT conv_id, turn, coalesce(role, 'user') AS role, turn AS at_turn, CAST(0 AS INTEGER) AS step,
       CAST(0 AS BIGINT) AS n_calls, CAST(0 AS BIGINT) AS n_linked, CAST(0 AS BIGINT) AS n_invalid, CAST(0 AS BIGINT) AS n_cyclic,
       '{"content":' || CAST(to_json(coalesce(text, '')) AS VARCHAR) || ',"role":' || CAST(to_json(coalesce(role, 'user')) AS VARCHAR) || '}' AS json
FROM conversations
"""

#: Turns made calls and results: a call's step is its place among the calls of its conversation, its result comes after it.
TOOL_CALLS = """
WITH c AS (SELECT conv_id, turn, role, text, len(string_split(text, ' ')) AS words FROM conversations)
SELECT c.conv_id, c.turn, c.role, CASE WHEN c.turn % 2 = 1 OR c.turn = 0 THEN c.turn ELSE c.turn - 1 END AS at_turn,
       CAST(CASE WHEN c.turn % 2 = 1 OR c.turn = 0 THEN 0 ELSE 1 + (c.turn - 2) // 2 END AS INTEGER) AS step,
       CAST(c.turn % 2 = 1 AS BIGINT) AS n_calls, CAST(c.turn % 2 = 1 AND n.turn IS NOT NULL AS BIGINT) AS n_linked,
       CAST(c.turn % 2 = 1 AND c.conv_id % 3 = 0 AS BIGINT) AS n_invalid, CAST(0 AS BIGINT) AS n_cyclic,
       '{"content":' || CASE WHEN c.turn % 2 = 1 THEN '""' ELSE CAST(to_json(c.text) AS VARCHAR) END || ',"role":"' || c.role || '"' ||
       CASE WHEN c.turn % 2 = 1 THEN ',"tool_calls":[{"arguments":{' || CASE WHEN c.turn > 1 THEN '"after":"{{c' || (c.turn - 2) || '}}",' ELSE '' END ||
            '"words":' || CASE WHEN c.conv_id % 3 = 0 THEN '"' || c.words || '"' ELSE CAST(c.words AS VARCHAR) END || '},"id":"c' || c.turn || '","name":"lookup"' ||
            CASE WHEN c.conv_id % 3 = 0 THEN ',"problems":["words:not integer"]' ELSE '' END || '}]'
            WHEN c.turn > 0 THEN ',"tool_call_id":"c' || (c.turn - 1) || '"' ELSE '' END || '}' AS json
FROM c LEFT JOIN c n ON n.conv_id = c.conv_id AND n.turn = c.turn + 1
"""

SQL: dict[str, str] = {"op5_chat_format": CHAT, "chat_tool_calls": TOOL_CALLS}
