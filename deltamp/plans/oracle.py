"""DuckDB SQL for the queries: always a full pass on the snapshot in question, so an incremental result agrees only if it is identical."""

from __future__ import annotations

_H = "((1000003*(a%1048576)+7919*(b%1048576)+42)%2147483647)"
_DAYS = "TIMESTAMP '1995-01-01' + to_days(({h}%2000)::INTEGER)"


def _simulated(pairs: str, timed: bool) -> str:
    """CTEs ending in ``log`` (t, op, a, b) from pairs (x, y[, t])."""
    t = "min(t)" if timed else _DAYS.format(h=_H)
    return f"""p0 AS ({pairs}), p1 AS (SELECT least(x, y) AS a, greatest(x, y) AS b{", t" if timed else ""} FROM p0 WHERE x <> y),
one AS (SELECT a, b, {t} AS t FROM p1 GROUP BY a, b),
log AS (SELECT t, 'add' AS op, a, b FROM one UNION ALL SELECT t + to_days((1 + {_H}%90)::INTEGER), 'del', a, b FROM one WHERE {_H}%5 = 0)"""


LOGS = {
    "user_item": """log AS (SELECT ts AS t, CASE WHEN event_type = 'error' THEN 'del' ELSE 'add' END AS op, least(user_id * 4, k * 4 + 1) AS a, greatest(user_id * 4, k * 4 + 1) AS b
  FROM (SELECT ts, user_id, event_type, (props->>'$.k')::BIGINT AS k FROM events) WHERE k IS NOT NULL AND user_id IS NOT NULL)""",
    "cust_part": _simulated("SELECT o_custkey * 4 AS x, l_partkey * 4 + 1 AS y, o_orderdate AS t FROM orders JOIN lineitem ON o_orderkey = l_orderkey", True),
    "part_supp": _simulated("SELECT l_partkey * 4 + 1 AS x, l_suppkey * 4 + 2 AS y, l_shipdate AS t FROM lineitem", True),
    "vec": _simulated("SELECT vec_id AS x, (vec_id * m + c) % (SELECT max(vec_id) + 1 FROM embeddings) AS y FROM embeddings, (VALUES (7, 3), (13, 5), (29, 11)) l(m, c)", False),
    "page_link": _simulated("SELECT DISTINCT page_id * 4 AS x, ('0x' || substr(md5(tok), 1, 10))::BIGINT * 4 + 1 AS y FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"/([^\"]*)\"', 1)) AS tok FROM pages)", False),
    "turns": _simulated("SELECT conv_id * 1000 + turn AS x, conv_id * 1000 + nx AS y FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nx FROM conversations) WHERE nx IS NOT NULL", False),
}

#: The newest changes, numbered from 0, and the log without them.
HELD = """nw AS (SELECT * FROM log ORDER BY t DESC, a DESC, b DESC LIMIT {n}), ch AS (SELECT *, row_number() OVER (ORDER BY t, a, b) - 1 AS seq FROM nw),
old AS (SELECT * FROM log WHERE (t, a, b) < (SELECT (t, a, b) FROM ch WHERE seq = 0))"""


def pairs(log: str, name: str) -> str:
    return f"{name}p AS (SELECT a, b FROM {log} GROUP BY a, b HAVING arg_max(op, t) = 'add'), {name} AS (SELECT a AS src, b AS dst FROM {name}p UNION ALL SELECT b, a FROM {name}p)"


NODES = "nodes AS (SELECT a AS node_id FROM log UNION SELECT b FROM log)"


def features(d: int) -> str:
    return f"feat AS MATERIALIZED (SELECT node_id, list_transform(range(0, {d}), lambda i: ((((node_id % 1048576) * (2 * i + 3) + 7919 * i + 42) * 40503) % 65521)::DOUBLE) AS v FROM nodes)"


def dense(v: str, out: int, n: int, shift: int = 0) -> str:
    return f"list_transform(range(0, {out}), lambda j: {v}[(3 * j + 1 + {shift}) % {n} + 1] + {v}[(5 * j + 2 + {shift}) % {n} + 1] - {v}[(7 * j + 4 + {shift}) % {n} + 1])"


def lifted(v: str) -> str:
    return f"list_transform({v}, lambda x: greatest(x + 65536, 0)::DOUBLE)"


def select(name: str, edges: str, messages: str, how: str, d: int) -> str:
    return f"""{name} AS MATERIALIZED (SELECT n.node_id, q.v FROM nodes n LEFT JOIN (SELECT dst, list(x ORDER BY i) AS v FROM (
  SELECT dst, i, {how}(v[i]) AS x FROM {edges} JOIN {messages} m ON src = m.node_id CROSS JOIN range(1, {d + 1}) r(i) GROUP BY dst, i) GROUP BY dst) q ON n.node_id = q.dst)"""


def forward(kind: str, k: int, d: int, how: str, edges: str = "e", prefix: str = "") -> tuple[str, list[str]]:
    """CTEs of a full pass from ``feat``: messages {prefix}m1 .. and aggregates {prefix}a1 ..; the last message is the output."""
    zero = "[" + ", ".join(["0.0"] * d) + "]::DOUBLE[]"
    first = dense("v", d, d) if kind == "gcn" else "v"
    out = [f"{prefix}m1 AS MATERIALIZED (SELECT node_id, {first} AS v FROM feat)"]
    for s in range(1, k + 1):
        m, a, nxt = f"{prefix}m{s}", f"{prefix}a{s}", f"{prefix}m{s + 1}"
        out.append(select(a, edges, m, how, d))
        x = f"coalesce(a.v, {zero})"
        if kind == "gcn":
            tail = lifted(x)
            out.append(f"{nxt}z AS MATERIALIZED (SELECT a.node_id, {tail} AS v FROM {a} a)")
            out.append(f"{nxt} AS MATERIALIZED (SELECT node_id, {dense('v', d, d) if s < k else 'v'} AS v FROM {nxt}z)")
        elif kind == "gcn_aggfirst":
            out.append(f"{nxt}z AS MATERIALIZED (SELECT a.node_id, {x} AS v FROM {a} a)")
            out.append(f"{nxt} AS MATERIALIZED (SELECT node_id, {lifted(dense('v', d, d))} AS v FROM {nxt}z)")
        elif kind == "sage":
            out.append(f"{nxt}z AS MATERIALIZED (SELECT a.node_id, {x} AS v, m.v AS w FROM {a} a JOIN {m} m USING (node_id))")
            out.append(f"{nxt}y AS MATERIALIZED (SELECT node_id, {dense('v', d, d)} AS v, {dense('w', d, d, 1)} AS w FROM {nxt}z)")
            out.append(f"{nxt} AS MATERIALIZED (SELECT node_id, list_transform(range(1, {d + 1}), lambda j: greatest(v[j] + w[j] + 65536, 0)::DOUBLE) AS v FROM {nxt}y)")
        else:
            out.append(f"{nxt}z AS MATERIALIZED (SELECT a.node_id, {x} AS v, m.v AS w FROM {a} a JOIN {m} m USING (node_id))")
            out.append(f"{nxt}y AS MATERIALIZED (SELECT node_id, list_transform(range(1, {d + 1}), lambda j: v[j] + w[j]) AS v FROM {nxt}z)")
            out.append(f"{nxt}x AS MATERIALIZED (SELECT node_id, {lifted(dense('v', d, d))} AS v FROM {nxt}y)")
            out.append(f"{nxt} AS MATERIALIZED (SELECT node_id, {lifted(dense('v', d, d))} AS v FROM {nxt}x)")
    return ",\n".join(out), f"{prefix}m{k + 1}"


def long(name: str, d: int, where: str = "") -> str:
    return f"SELECT node_id, (i - 1)::INTEGER AS dim, v[i] AS val FROM {name} CROSS JOIN range(1, {d + 1}) r(i) {where}"


def full(graph: str, kind: str, k: int, d: int, how: str, tail: str | None = None) -> str:
    ctes, last = forward(kind, k, d, how)
    return f"WITH {LOGS[graph]},\n{pairs('log', 'e')},\n{NODES},\n{features(d)},\n{ctes}\n" + (tail or long(last, d)).replace("{last}", last)


def both(graph: str, held: int, kind: str, k: int, d: int, how: str, tail: str) -> str:
    """Full passes on the snapshots before (prefix b, edges eb) and after (prefix c, edges e) the held-out changes, and their net delta."""
    before, _ = forward(kind, k, d, how, "eb", "b")
    after, _ = forward(kind, k, d, how, "e", "c")
    return f"WITH {LOGS[graph]},\n{HELD.format(n=held)},\n{pairs('log', 'e')},\n{pairs('old', 'eb')},\n{NODES},\n{features(d)},\n{before},\n{after},\n" + DELTA + tail


DELTA = """delta AS (SELECT src, dst, 'add' AS op FROM (SELECT * FROM e EXCEPT SELECT * FROM eb) UNION ALL SELECT src, dst, 'del' FROM (SELECT * FROM eb EXCEPT SELECT * FROM e))
"""


def ball(k: int, edges: str, seeds: str) -> str:
    """CTEs h0 .. hk: nodes within so many hops of the seeds."""
    out = [f"h0 AS ({seeds})"]
    for i in range(1, k + 1):
        out.append(f"h{i} AS (SELECT node_id FROM h{i - 1} UNION SELECT dst FROM {edges} JOIN h{i - 1} ON src = node_id)")
    return ",\n".join(out)


def graph_only(graph: str, held: int, tail: str) -> str:
    return f"WITH {LOGS[graph]},\n{HELD.format(n=held)},\n{pairs('log', 'e')},\n{pairs('old', 'eb')},\n{NODES},\n" + DELTA + tail
