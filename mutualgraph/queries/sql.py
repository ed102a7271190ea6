"""SQL of the shared relations, as common table expressions that every oracle begins with."""

NET1 = """
users1 AS (SELECT c_custkey AS user_id FROM customer),
posts1 AS (SELECT o_orderkey AS post_id, o_custkey AS user_id FROM orders),
attr1 AS (SELECT DISTINCT l_orderkey AS post_id, 'word' AS kind, CAST(l_partkey AS VARCHAR) AS attr FROM lineitem
  UNION ALL SELECT DISTINCT l_orderkey, 'location', CAST(l_suppkey AS VARCHAR) FROM lineitem
  UNION ALL SELECT o_orderkey, 'time', strftime(o_orderdate, '%Y-%m-%d') FROM orders),
follow1 AS (SELECT DISTINCT u AS src, p AS dst FROM (
  SELECT o_custkey AS u, lag(o_custkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey) AS p
  FROM (SELECT DISTINCT l_partkey, o_orderkey, o_orderdate, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey)) WHERE p <> u)"""

NET2 = """
e2 AS (SELECT event_id, ts, user_id, event_type, value, CAST(regexp_extract(props, '([0-9]+)', 1) AS INTEGER) AS k FROM events),
users2 AS (SELECT DISTINCT user_id FROM e2),
posts2 AS (SELECT event_id AS post_id, user_id FROM e2),
attr2 AS (SELECT event_id AS post_id, 'word' AS kind, event_type || ':' || CAST(CAST(floor(value / 10) AS BIGINT) AS VARCHAR) AS attr FROM e2
  UNION ALL SELECT event_id, 'location', CAST(k AS VARCHAR) FROM e2
  UNION ALL SELECT event_id, 'time', strftime(ts, '%Y-%m-%d %H') FROM e2),
follow2 AS (SELECT DISTINCT u AS src, p AS dst FROM (
  SELECT user_id AS u, ts, lag(user_id) OVER w AS p, lag(ts) OVER w AS t FROM e2 WINDOW w AS (PARTITION BY k ORDER BY ts, event_id))
  WHERE p <> u AND epoch_us(ts) - epoch_us(t) <= 3600000000)"""

ANCHORS = "anchors AS (SELECT c_custkey AS u1, c_custkey AS u2 FROM customer WHERE c_custkey IN (SELECT user_id FROM events) AND (c_custkey * 7919 + 13) % 100 < 63)"
PART1 = "part1 AS (SELECT c_custkey AS user_id, c_nationkey % 10 AS cluster FROM customer)"
PART2 = "part2 AS (SELECT DISTINCT user_id, CAST(user_id % 10 AS INTEGER) AS cluster FROM events)"


def document_view(side: int, n: int) -> str:
    """CTEs of a document view, as network n."""
    a, b, c, d = ((31, 7, 17, 3), (37, 11, 13, 5))[side]
    return f"""
docs{n} AS (SELECT * FROM documents WHERE doc_id % 5 <> {side}),
users{n} AS (SELECT doc_id AS user_id FROM docs{n}),
lines{n} AS (SELECT * FROM (SELECT doc_id, source, unnest(range(len(string_split(text, chr(10))))) AS line, unnest(string_split(text, chr(10))) AS body FROM docs{n}) WHERE line % 2 = {side}),
posts{n} AS (SELECT doc_id * 2147483648 + line AS post_id, doc_id AS user_id FROM lines{n}),
words{n} AS (SELECT doc_id, doc_id * 2147483648 + line AS post_id, unnest(list_distinct(regexp_extract_all(lower(body), '\\p{{L}}{{3,}}'))) AS attr FROM lines{n}),
held{n} AS (SELECT attr FROM words{n} GROUP BY attr HAVING count(DISTINCT doc_id) >= 2 AND count(DISTINCT doc_id) <= 0.05 * (SELECT count(*) FROM docs{n})),
attr{n} AS (SELECT DISTINCT post_id, 'word' AS kind, attr FROM words{n} JOIN held{n} USING (attr) UNION SELECT DISTINCT doc_id * 2147483648 + line, 'location', source FROM lines{n}),
follow{n} AS (SELECT DISTINCT src, dst FROM (
  SELECT doc_id AS src, lead(doc_id) OVER (PARTITION BY lang ORDER BY doc_id) AS dst FROM docs{n}
  UNION ALL SELECT doc_id, unnest([(doc_id * {a} + {b}) % (SELECT max(doc_id) + 1 FROM docs{n}), (doc_id * {c} + {d}) % (SELECT max(doc_id) + 1 FROM docs{n})]) FROM docs{n})
  WHERE src <> dst AND dst IN (SELECT user_id FROM users{n}))"""


def net(n: int) -> str:
    return {1: NET1, 2: NET2}.get(n) or document_view(n - 3, n)


def counts(n: int, path: int, name: str | None = None, self_paths: bool = False) -> str:
    """CTEs that end with p<path> (src, dst, cnt)."""
    name = name or f"p{path}"
    off = "TRUE" if self_paths else "x <> y"
    if path == 1:
        return f"{name} AS (SELECT src, dst, 1 AS cnt FROM follow{n})"
    if path in (2, 3, 4):
        x, y, on = {2: ("a.src", "b.dst", "a.dst = b.src"), 3: ("a.src", "b.src", "a.dst = b.dst"), 4: ("a.dst", "b.dst", "a.src = b.src")}[path]
        body = f"SELECT {x} AS x, {y} AS y, 1 AS c FROM follow{n} a JOIN follow{n} b ON {on}"
    else:
        kind = {5: "word", 6: "time", 7: "location"}[path]
        inc = f"(SELECT user_id, attr, count(*) AS cnt FROM posts{n} JOIN attr{n} USING (post_id) WHERE kind = '{kind}' GROUP BY 1, 2)"
        body = f"SELECT a.user_id AS x, b.user_id AS y, a.cnt * b.cnt AS c FROM {inc} a JOIN {inc} b USING (attr)"
    return f"{name} AS (SELECT x AS src, y AS dst, sum(c) AS cnt FROM ({body}) WHERE {off} GROUP BY 1, 2)"


def marginals(path: int, of: str | None = None) -> str:
    of = of or f"p{path}"
    return f"""m{path} AS (SELECT user_id, sum(o) AS o, sum(i) AS i FROM (SELECT src AS user_id, cnt AS o, 0 AS i FROM {of} UNION ALL SELECT dst, 0, cnt FROM {of}) GROUP BY 1)"""


def similarity(path: int, form: str = "pair") -> str:
    """s<path> (src, dst, s) from p<path> and m<path>."""
    below = "(a.o + b.o)" if form == "pair" else "(a.o + a.i)"
    return f"""s{path} AS (SELECT q.src, q.dst, q.cnt * 1.0 / {below} AS s
  FROM (SELECT src, dst, sum(cnt) AS cnt FROM (SELECT src, dst, cnt FROM p{path} UNION ALL SELECT dst, src, cnt FROM p{path}) GROUP BY 1, 2) q
  JOIN m{path} a ON a.user_id = q.src JOIN m{path} b ON b.user_id = q.dst)"""


def closeness(n: int, weights: dict[int, float], form: str = "pair") -> str:
    """CTEs that end with S (src, dst, s)."""
    parts = [net(n)]
    for p in weights:
        parts += [counts(n, p), marginals(p), similarity(p, form)]
    union = " UNION ALL ".join(f"SELECT src, dst, {w!r} * s AS s FROM s{p}" for p, w in weights.items())
    parts.append(f"S AS (SELECT src, dst, sum(s) AS s FROM ({union}) GROUP BY 1, 2)")
    return ",\n".join(parts)


UNIFORM = {p: 1 / 7 for p in range(1, 8)}
