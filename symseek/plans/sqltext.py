"""SQL texts that compute the same results in an engine with recursive queries: the independent side of the comparison."""

from __future__ import annotations

# Streams on the given tables, as SQL.
EVENTS = "(SELECT user_id AS stream_id, count(*) AS n, string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY ts, event_id) AS text FROM events GROUP BY user_id)"
EVENTS_ALL = "(SELECT 0::BIGINT AS stream_id, count(*) AS n, string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY ts, event_id) AS text FROM events)"
_LINE_ORDER = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey"
LINES4 = f"(SELECT l_suppkey AS stream_id, count(*) AS n, string_agg(substr('acgt', l_quantity::INTEGER % 4 + 1, 1), '' ORDER BY {_LINE_ORDER}) AS text FROM lineitem GROUP BY l_suppkey)"
LINES16 = f"(SELECT l_suppkey % 16 AS stream_id, count(*) AS n, string_agg(substr('ABCD', l_quantity::INTEGER % 4 + 1, 1), '' ORDER BY {_LINE_ORDER}) AS text FROM lineitem GROUP BY 1)"
LINES_ABCD = LINES4.replace("acgt", "ABCD")
LINES100 = LINES16.replace("% 16", "% 100")
LINES6 = f"(SELECT l_partkey AS stream_id, count(*) AS n, string_agg(substr('ABCDEF', instr('AFANRFRNAONO', l_returnflag || l_linestatus) // 2 + 1, 1), '' ORDER BY {_LINE_ORDER}) AS text FROM lineitem GROUP BY l_partkey)"
ORDERS = "(SELECT o_custkey AS stream_id, count(*) AS n, string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey) AS text FROM orders GROUP BY o_custkey)"
ORDERS_ABC = f"(SELECT stream_id, n, translate(text, 'FOP', 'ABC') AS text FROM {ORDERS})"
PRIORITIES = "(SELECT o_custkey AS stream_id, count(*) AS n, string_agg(substr(o_orderpriority, 1, 1), '' ORDER BY o_orderdate, o_orderkey) AS text FROM orders GROUP BY o_custkey)"
_FOLD = "regexp_replace(lower({}), '[^a-z ]', '?', 'g')"


def docs(where: str) -> str:
    return f"(SELECT doc_id AS stream_id, length(text) AS n, {_FOLD.format('text')} AS text FROM documents WHERE {where})"


def pages(where: str = "true") -> str:
    return f"(SELECT page_id AS stream_id, length(html) AS n, regexp_replace(html, '[^ -~]', '?', 'g') AS text FROM pages WHERE {where})"


CONVERSATIONS = f"(SELECT conv_id AS stream_id, sum(length(text))::BIGINT AS n, string_agg({_FOLD.format('text')}, '' ORDER BY turn) AS text FROM conversations GROUP BY conv_id)"
EMBEDDINGS = "(SELECT vec_id AS stream_id, len(embedding)::BIGINT AS n, array_to_string(list_transform(embedding, lambda x: CASE WHEN x < -0.1 THEN 'a' WHEN x < 0 THEN 'b' WHEN x < 0.1 THEN 'c' ELSE 'd' END), '') AS text FROM embeddings)"


def cut(streams: str, count: int) -> str:
    return f"(SELECT stream_id, least(n, {count})::BIGINT AS n, substr(text, 1, {count}) AS text FROM {streams})"


def patterns(rows) -> str:
    return "(SELECT pattern_id, pattern, length(pattern)::INTEGER AS lp, k_max FROM (VALUES " + ", ".join(f"({i}, '{p}', {k})" for i, p, k in rows) + ") v(pattern_id, pattern, k_max))"


def hits(streams: str, pats: str) -> str:
    """All hits, by the distance of every substring of a fitting length."""
    return f"""(
  SELECT stream_id, pattern_id, start, len, dist FROM (
    SELECT stream_id, pattern_id, k_max, start, len::INTEGER AS len, levenshtein(pattern, substr(text, (start + 1)::BIGINT, len::BIGINT))::INTEGER AS dist
    FROM (SELECT *, unnest(range(greatest(lp - k_max, 1), least(lp + k_max, n - start) + 1)) AS len
          FROM (SELECT *, unnest(range(0, n)) AS start FROM {streams} s CROSS JOIN {pats} p)))
  WHERE dist <= k_max)"""


def ends(hits_sql: str) -> str:
    return f'(SELECT stream_id, pattern_id, start + len - 1 AS "end", min(dist)::INTEGER AS dist FROM {hits_sql} GROUP BY ALL)'


def islands(hits_sql: str) -> str:
    return f"""(
  SELECT stream_id, pattern_id, start, len, dist, (sum(fresh) OVER (PARTITION BY stream_id, pattern_id ORDER BY start, len ROWS UNBOUNDED PRECEDING) - 1)::BIGINT AS island FROM (
    SELECT *, CASE WHEN start > coalesce(max(start + len - 1) OVER (PARTITION BY stream_id, pattern_id ORDER BY start, len ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), -1) THEN 1 ELSE 0 END AS fresh
    FROM {hits_sql}))"""


def sift(hits_sql: str, k: int, *, tie: str = "earliest", validation: str = "accumulated", strict: bool = True) -> str:
    """The online rules as a recursion over the hits of each stream and pattern, one hit a step. A closing row stands at the end of each stream."""
    levels = range(k + 1)
    nothing = ", ".join(f"NULL::BIGINT AS s{j}, NULL::INTEGER AS l{j}" for j in levels)
    last = "CASE leader " + " ".join(f"WHEN {j} THEN s{j} + l{j} - 1" for j in levels) + " END"
    more, less = (">", "<") if strict else (">=", "<")
    query = f"SELECT x.*, h.r AS hr, h.start AS hs, h.len AS hl, h.dist AS hd, {last} AS upto FROM x JOIN ranked h ON h.stream_id = x.stream_id AND h.pattern_id = x.pattern_id AND h.r = x.r + 1"
    query = f"SELECT *, leader IS NOT NULL AND hs > upto AS shut, 0::BIGINT AS t_0, 0::BIGINT AS q_0, NULL::BIGINT AS m_0 FROM ({query})"
    for j in levels:
        if validation == "interval":
            clear = f"s{j} + l{j} - 1 {less} m_{j}" + (" - 1" if strict else "")
        else:
            clear = f"upto - s{j} + 1 - {'t' if validation == 'accumulated' else 'q'}_{j} {more} l{j}"
        query = f"SELECT *, shut AND s{j} IS NOT NULL AND leader <= {j} AND (leader = {j} OR {clear}) AS a{j} FROM ({query})"
        query = f"SELECT *, CASE WHEN a{j} THEN t_{j} + l{j} ELSE t_{j} END AS t_{j + 1}, CASE WHEN a{j} THEN l{j} ELSE q_{j} END AS q_{j + 1}, CASE WHEN a{j} THEN least(coalesce(m_{j}, s{j}), s{j}) ELSE m_{j} END AS m_{j + 1} FROM ({query})"
    pending = "CASE leader " + " ".join(f"WHEN {j} THEN l{j}" for j in levels) + " END"
    tied = {"earliest": "false", "latest": "true", "shortest": f"hl < {pending}"}[tie]
    query = f"SELECT *, hd IS NOT NULL AND (leader IS NULL OR shut OR hd < leader OR (hd = leader AND {tied})) AS takes FROM ({query})"
    step = ", ".join(f"CASE WHEN takes AND hd = {j} THEN hs WHEN shut THEN NULL ELSE s{j} END, CASE WHEN takes AND hd = {j} THEN hl WHEN shut THEN NULL ELSE l{j} END" for j in levels)
    given = ", ".join(f"CASE WHEN a{j} THEN s{j} END, CASE WHEN a{j} THEN l{j} END" for j in levels)
    none = ", ".join(f"NULL::BIGINT AS e{j}, NULL::INTEGER AS f{j}" for j in levels)
    names = ", ".join(f"s{j}, l{j}" for j in levels) + ", fin, " + ", ".join(f"e{j}, f{j}" for j in levels)
    out = " UNION ALL ".join(f"SELECT stream_id, pattern_id, e{j} AS start, f{j} AS len, {j} AS dist, fin AS decided_at FROM x WHERE e{j} IS NOT NULL" for j in levels)
    return f"""(
  WITH RECURSIVE found AS MATERIALIZED {hits_sql},
  ranked AS MATERIALIZED (
    SELECT *, row_number() OVER (PARTITION BY stream_id, pattern_id ORDER BY start, len) AS r FROM (
      SELECT stream_id, pattern_id, start, len, dist FROM found
      UNION ALL SELECT stream_id, pattern_id, 9000000000000, 1, NULL FROM (SELECT DISTINCT stream_id, pattern_id FROM found))
  ),
  x(stream_id, pattern_id, r, leader, {names}) AS (
    SELECT DISTINCT stream_id, pattern_id, 0::BIGINT, NULL::INTEGER, {nothing}, NULL::BIGINT, {none} FROM found
    UNION ALL
    SELECT stream_id, pattern_id, hr, CASE WHEN takes THEN hd WHEN shut THEN NULL ELSE leader END, {step}, upto, {given} FROM ({query})
  )
  SELECT stream_id, pattern_id, start, len, dist::INTEGER AS dist, decided_at,
         (dense_rank() OVER (PARTITION BY stream_id, pattern_id ORDER BY decided_at) - 1)::BIGINT AS group_no FROM ({out}))"""


def all_of(relation: str) -> str:
    return f"SELECT * FROM {relation}"
