"""Oracle SQL: the workloads, and the iterative methods unrolled into chains of common table expressions."""

from __future__ import annotations

from semtrie.functions.hashing import sql_hash as h

ACCESS1 = """c_access AS MATERIALIZED (
  SELECT o_custkey AS user_id, l_partkey AS doc_id, o_orderdate AS ts, l_shipdate AS ts2, l_orderkey AS tie, l_linenumber AS tie2
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"""

VEC = "vec AS MATERIALIZED (SELECT vec_id AS doc_id, CAST(embedding AS DOUBLE[]) AS emb FROM embeddings)"

ACCESS2 = """pool AS MATERIALIZED (
  SELECT vec_id, label, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS pos, count(*) OVER (PARTITION BY label) AS n FROM embeddings),
ev AS MATERIALIZED (SELECT *, CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS BIGINT) AS k FROM events),
access AS MATERIALIZED (
  SELECT user_id, vec_id AS doc_id, ts, event_id AS tie FROM ev JOIN pool ON label = user_id % 10 AND pos = k % n WHERE event_type IN ('view', 'click', 'purchase')
  UNION ALL SELECT user_id, k * ((SELECT count(*) FROM embeddings) // 100), ts, event_id FROM ev WHERE event_type IN ('error', 'signup')),
holding AS MATERIALIZED (SELECT DISTINCT user_id, doc_id FROM access)"""

SPLIT2 = ACCESS2 + f""",
parts AS MATERIALIZED (
  SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY {h("'42'", "user_id", "doc_id")}, doc_id) <= 10 AS is_test
  FROM holding WHERE user_id IN (SELECT user_id FROM holding GROUP BY user_id HAVING count(*) >= 30)),
train AS MATERIALIZED (SELECT user_id, doc_id FROM parts WHERE NOT is_test)"""



PROFILE2 = SPLIT2 + ", " + VEC + """,
profile AS MATERIALIZED (
  SELECT user_id, any_value(n) AS n_docs, list(m ORDER BY d) AS emb FROM (
    SELECT user_id, d, avg(x) AS m, count(*) AS n FROM (SELECT user_id, unnest(emb) AS x, unnest(range(0, len(emb))) AS d FROM train JOIN vec USING (doc_id)) GROUP BY 1, 2)
  GROUP BY 1),
sims AS MATERIALIZED (
  SELECT a.user_id, b.user_id AS peer_id, list_cosine_similarity(a.emb, b.emb) AS sim FROM profile a CROSS JOIN profile b WHERE a.user_id <> b.user_id)"""

QUERIES2 = """queries AS MATERIALIZED (
  SELECT user_id * 100000 + doc_id AS query_id, user_id, doc_id AS target_doc, emb FROM parts JOIN vec USING (doc_id) WHERE is_test)"""

#: The stand-in trie of the oracles: eight leaves by hash; every fourth user also in the sibling leaf.
PLACES2 = f"""places AS MATERIALIZED (
  SELECT user_id, lpad(bin({h("'leaf'", "user_id")} % 8), 3, '0') AS path FROM profile
  UNION SELECT user_id, left(p, 2) || CASE right(p, 1) WHEN '0' THEN '1' ELSE '0' END
  FROM (SELECT user_id, lpad(bin({h("'leaf'", "user_id")} % 8), 3, '0') AS p FROM profile WHERE {h("'clone'", "user_id")} % 4 = 0))"""

DIST3 = "CASE WHEN a.path = b.path THEN 0 WHEN left(a.path, 2) = left(b.path, 2) THEN 2 WHEN left(a.path, 1) = left(b.path, 1) THEN 4 ELSE 6 END"


def contacts_sql(n_cc: int) -> str:
    return f"""met AS MATERIALIZED (
  SELECT a.user_id, a.path, b.user_id AS peer_id, min({{'ring': {DIST3}, 'other': b.path}}) AS near
  FROM places a JOIN places b ON a.user_id <> b.user_id GROUP BY ALL),
contacts AS MATERIALIZED (
  SELECT user_id, path, peer_id, near.ring AS ring FROM (
    SELECT met.*, row_number() OVER (PARTITION BY user_id, path ORDER BY near.ring, near.other,
      CASE WHEN near.ring = 0 THEN -round(sim, 12) ELSE CAST({h("'42'", "'contact'", "peer_id")} AS DOUBLE) END, peer_id) AS rn
    FROM met JOIN sims USING (user_id, peer_id)) WHERE rn <= {n_cc}),
known0 AS MATERIALIZED (SELECT DISTINCT user_id, peer_id, sim, 0 AS added_round FROM contacts JOIN sims USING (user_id, peer_id))"""


def rounds_sql(rounds: int, n_cu: int, *, ask_from: str = "closest", reply_limit: int | None = None, everything: bool = False, start: str = "known") -> str:
    """known1 .. knownR from known0, one snapshot per round."""
    out = []
    for t in range(1, rounds + 1):
        k = f"{start}{t - 1}"
        limit = f"rank <= {n_cu}" if ask_from == "closest" else "true"
        test = "true" if everything else "(bar IS NULL OR round(v.sim, 12) > round(bar, 12))"
        keep = f"WHERE rn <= {reply_limit}" if reply_limit else ""
        out.append(f"""{start}_r{t} AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY round(sim, 12) DESC, peer_id) AS rank FROM {k}),
{start}_s{t} AS MATERIALIZED (SELECT user_id, count(*) FILTER (WHERE {limit}) AS n, max(sim) FILTER (WHERE rank = {n_cu}) AS bar FROM {start}_r{t} GROUP BY 1),
{start}_a{t} AS MATERIALIZED (
  SELECT s.user_id, r.peer_id AS asked, s.bar FROM {start}_s{t} s JOIN {start}_r{t} r ON r.user_id = s.user_id AND r.rank = {h("'42'", f"'{t}'", "s.user_id")} % s.n + 1),
{start}{t} AS MATERIALIZED (
  SELECT * FROM {k} UNION ALL SELECT user_id, peer_id, sim, {t} FROM (
    SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY round(sim, 12) DESC, peer_id) AS rn FROM (
      SELECT a.user_id, t.peer_id, v.sim FROM {start}_a{t} a JOIN {k} t ON t.user_id = a.asked AND t.peer_id <> a.user_id
      JOIN sims v ON v.user_id = a.user_id AND v.peer_id = t.peer_id
      WHERE {test} AND NOT EXISTS (SELECT 1 FROM {k} o WHERE o.user_id = a.user_id AND o.peer_id = t.peer_id))) {keep})""")
    return ",\n".join(out)


def truth_sql(k: int) -> str:
    return f"truth AS MATERIALIZED (SELECT user_id, peer_id, sim, rank FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY round(sim, 12) DESC, peer_id) AS rank FROM sims) WHERE rank <= {k})"


def recall_sql(k: str, n_cu: int, label: str) -> str:
    return f"""SELECT {label}, CAST(count(*) AS BIGINT) AS users, round(avg(hits), 6) AS recall FROM (
  SELECT t.user_id, count(c.peer_id) AS hits FROM truth t LEFT JOIN (
    SELECT user_id, peer_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY round(sim, 12) DESC, peer_id) AS rk FROM {k}) WHERE rk <= {n_cu}) c
  ON c.user_id = t.user_id AND c.peer_id = t.peer_id GROUP BY t.user_id)"""


def hops_sql(max_hops: int, lists: str, *, count_self: bool = False, revisit: bool = False, vectors: str = "profile") -> str:
    """walk0 .. walkL and trace: greedy routing over ``lists(user_id, peer_id)``."""
    first = 1 if count_self else 0
    status = lambda hop: f"CASE WHEN EXISTS (SELECT 1 FROM train t WHERE t.user_id = cur AND t.doc_id = target_doc) THEN 'found' WHEN {hop} >= {max_hops} THEN 'max_hops' ELSE 'open' END"
    out = [f"walk0 AS MATERIALIZED (SELECT query_id, cur, target_doc, emb, [cur] AS visited, {first} AS hop, {status(first)} AS status FROM (SELECT query_id, user_id AS cur, target_doc, emb FROM queries))"]
    steps = max_hops - first
    free = "true" if revisit else "NOT list_contains(w.visited, l.peer_id)"
    for i in range(1, steps + 1):
        out.append(f"""next{i} AS MATERIALIZED (
  SELECT w.query_id, arg_max(l.peer_id, {{'s': round(list_cosine_similarity(w.emb, p.emb), 12), 'i': -l.peer_id}}) AS nxt
  FROM walk{i - 1} w JOIN {lists} l ON l.user_id = w.cur JOIN {vectors} p ON p.user_id = l.peer_id WHERE w.status = 'open' AND {free} GROUP BY 1),
walk{i} AS MATERIALIZED (
  SELECT query_id, cur, target_doc, emb, visited, {first + i} AS hop, {status(first + i)} AS status FROM (
    SELECT w.query_id, n.nxt AS cur, w.target_doc, w.emb, list_append(w.visited, n.nxt) AS visited FROM walk{i - 1} w JOIN next{i} n USING (query_id) WHERE w.status = 'open')
  UNION ALL SELECT w.query_id, w.cur, w.target_doc, w.emb, w.visited, w.hop, 'dead_end' FROM walk{i - 1} w WHERE w.status = 'open' AND w.query_id NOT IN (SELECT query_id FROM next{i}))""")
    out.append("trace AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT query_id, hop, cur AS user_id, status FROM walk{i}" for i in range(steps + 1)) + ")")
    out.append("outcome AS MATERIALIZED (SELECT query_id, arg_max({'s': status, 'h': hop}, {'h': hop, 'd': CAST(status = 'dead_end' AS INT)}) AS e FROM trace GROUP BY 1)")
    return ",\n".join(out)


def trie_sql(levels: int, capacity: int, delta: float, steps: int = 20, *, clone_on_split: bool = False, unit: bool = False, source: str = "") -> str:
    """node and placement tables of a trie of at most ``levels`` splits in depth over one user per vector.

    The level-synchronous build: heads by arrival, a farthest-pair start, a fixed
    number of averaging steps (those after the last change repeat it), routing
    with clones.  With levels to spare it is the whole trie.
    """
    emb = "list_transform(emb, lambda x: x / sqrt(list_dot_product(emb, emb)))" if unit else "emb"
    src = source or f"SELECT doc_id AS user_id, {emb} AS emb FROM vec"
    out = [VEC, f"m0 AS MATERIALIZED (SELECT '' AS path, user_id, {h("'42'", "'arrival'", "user_id")} AS arrival, emb FROM ({src}))"]
    mean = lambda rel, keys: f"(SELECT {keys}, list(m ORDER BY d) AS c FROM (SELECT {keys}, d, avg(x) AS m FROM (SELECT {keys}, unnest(emb) AS x, unnest(range(0, 64)) AS d FROM {rel}) GROUP BY ALL) GROUP BY ALL)"
    for n in range(levels):
        out.append(f"""o{n} AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY path ORDER BY arrival, user_id) AS rn, count(*) OVER (PARTITION BY path) AS cnt FROM m{n}),
hd{n} AS MATERIALIZED (SELECT path, user_id, arrival, emb FROM o{n} WHERE cnt > {capacity} AND rn <= {capacity + 1}),
s1_{n} AS MATERIALIZED (SELECT x.path, arg_max(x.emb, {{'d': list_distance(x.emb, c.c), 'a': -x.arrival}}) AS c0 FROM hd{n} x JOIN {mean(f"hd{n}", "path")} c USING (path) GROUP BY 1),
k{n}_0 AS MATERIALIZED (SELECT x.path, any_value(c0) AS c0, arg_max(x.emb, {{'d': list_distance(x.emb, c0), 'a': -x.arrival}}) AS c1 FROM hd{n} x JOIN s1_{n} USING (path) GROUP BY 1)""")
        for i in range(1, steps + 1):
            out.append(f"""g{n}_{i} AS MATERIALIZED (SELECT x.path, x.emb, CAST(list_distance(x.emb, c0) > list_distance(x.emb, c1) AS INT) AS side FROM hd{n} x JOIN k{n}_{i - 1} USING (path)),
k{n}_{i} AS MATERIALIZED (
  SELECT k.path, coalesce(a.c, k.c0) AS c0, coalesce(b.c, k.c1) AS c1 FROM k{n}_{i - 1} k
  LEFT JOIN {mean(f"(SELECT path, emb FROM g{n}_{i} WHERE side = 0)", "path")} a ON a.path = k.path LEFT JOIN {mean(f"(SELECT path, emb FROM g{n}_{i} WHERE side = 1)", "path")} b ON b.path = k.path)""")
        head = "true" if clone_on_split else f"rn > {capacity + 1}"
        out.append(f"""d{n} AS MATERIALIZED (
  SELECT o.*, list_distance(o.emb, c0) AS d0, list_distance(o.emb, c1) AS d1 FROM o{n} o JOIN k{n}_{steps} USING (path) WHERE cnt > {capacity}),
m{n + 1} AS MATERIALIZED (
  SELECT path || CASE WHEN d0 <= d1 THEN '0' ELSE '1' END AS path, user_id, arrival, emb FROM d{n}
  UNION ALL SELECT path || CASE WHEN d0 <= d1 THEN '1' ELSE '0' END, user_id, arrival, emb FROM d{n} WHERE abs(d0 - d1) < {delta!r} AND {head})""")
    parts = [f"SELECT path, user_id FROM o{n} WHERE cnt <= {capacity}" for n in range(levels)] + [f"SELECT path, user_id FROM m{levels}"]
    out.append("placement AS MATERIALIZED (" + " UNION ALL ".join(parts) + ")")
    splits = " UNION ALL ".join(f"SELECT DISTINCT path, cnt AS n FROM o{n} WHERE cnt > {capacity}" for n in range(levels))
    out.append(f"splits AS MATERIALIZED ({splits})")
    return ",\n".join(out)


def frozen_sql(levels: int, delta: float, source: str, steps: int = 20) -> str:
    """landed(user_id, path): where the rows of ``source`` (user_id, emb) end in the finished trie of ``trie_sql``."""
    out = [f"f0 AS MATERIALIZED (SELECT user_id, '' AS path, emb FROM ({source}))"]
    for n in range(levels):
        out.append(f"""z{n} AS MATERIALIZED (SELECT f.*, list_distance(f.emb, c0) AS d0, list_distance(f.emb, c1) AS d1 FROM f{n} f JOIN k{n}_{steps} USING (path)),
f{n + 1} AS MATERIALIZED (
  SELECT user_id, path || CASE WHEN d0 <= d1 THEN '0' ELSE '1' END AS path, emb FROM z{n}
  UNION ALL SELECT user_id, path || CASE WHEN d0 <= d1 THEN '1' ELSE '0' END, emb FROM z{n} WHERE abs(d0 - d1) < {delta!r})""")
    ends = [f"SELECT user_id, path FROM f{n} WHERE path NOT IN (SELECT path FROM k{n}_{steps})" for n in range(levels)] + [f"SELECT user_id, path FROM f{levels}"]
    out.append("landed AS MATERIALIZED (" + " UNION ALL ".join(ends) + ")")
    return ",\n".join(out)


def diffuse_sql(alpha: float, steps: int, edges: str) -> str:
    """v0 .. vT: repeated mixing of own vectors with the mean of the neighbours'."""
    out = ["v0 AS MATERIALIZED (SELECT user_id, emb FROM profile)"]
    for i in range(1, steps + 1):
        out.append(f"""n{i} AS MATERIALIZED (
  SELECT user_id, list(m ORDER BY d) AS around FROM (
    SELECT user_id, d, avg(x) AS m FROM (SELECT e.src AS user_id, unnest(v.emb) AS x, unnest(range(0, 64)) AS d FROM {edges} e JOIN v{i - 1} v ON v.user_id = e.dst) GROUP BY 1, 2) GROUP BY 1),
v{i} AS MATERIALIZED (
  SELECT p.user_id, CASE WHEN around IS NULL THEN p.emb ELSE list_transform(list_zip(p.emb, around), lambda z: {alpha!r} * z[1] + {1 - alpha!r} * z[2]) END AS emb FROM profile p LEFT JOIN n{i} USING (user_id))""")
    return ",\n".join(out)


def numbered_sql(users: str = "profile") -> str:
    return f"numbered AS MATERIALIZED (SELECT user_id, row_number() OVER (ORDER BY {h("'number'", "user_id")}, user_id) - 1 AS number FROM (SELECT DISTINCT user_id FROM {users}))"


def pa_sql(m: int, seed: int = 42) -> str:
    """edges(src, dst) of preferential attachment: every odd endpoint slot retraces to an even one."""
    draw = h(f"'{seed}'", "'pa'", "slot // 2")
    return f"""slots AS MATERIALIZED (
  WITH RECURSIVE r AS (
    SELECT number * {m} + j AS e, 2 * (number * {m} + j) + 1 AS slot FROM numbered CROSS JOIN (SELECT unnest(range(0, {m})) AS j)
    UNION ALL SELECT e, {draw} % slot AS slot FROM r WHERE slot % 2 = 1)
  SELECT e, slot // 2 AS e2 FROM r WHERE slot % 2 = 0),
pairs AS MATERIALIZED (SELECT DISTINCT e // {m} AS a, e2 // {m} AS b FROM slots WHERE e // {m} <> e2 // {m}),
one AS MATERIALIZED (SELECT x.user_id AS src, y.user_id AS dst FROM pairs JOIN numbered x ON x.number = a JOIN numbered y ON y.number = b),
pa AS MATERIALIZED (SELECT src, dst FROM one UNION SELECT dst, src FROM one)"""


def random_lists_sql(known: str, out: str = "rlists", users: str = "numbered", seed: int = 42) -> str:
    return f"""{out}_w AS MATERIALIZED (SELECT user_id, least(count(*), (SELECT count(*) - 1 FROM {users})) AS k FROM {known} GROUP BY 1),
{out}_d AS MATERIALIZED (SELECT user_id, k, i, {h(f"'{seed}'", "'list'", "user_id", "i")} % (SELECT count(*) FROM {users}) AS number FROM (SELECT user_id, k, unnest(range(0, k * 4 + 41)) AS i FROM {out}_w WHERE 2 * k <= (SELECT count(*) FROM {users}))),
{out} AS MATERIALIZED (
  SELECT user_id, peer_id FROM (
    SELECT d.user_id, n.user_id AS peer_id, any_value(k) AS k, row_number() OVER (PARTITION BY d.user_id ORDER BY min(i)) AS rn
    FROM {out}_d d JOIN {users} n USING (number) WHERE d.user_id <> n.user_id GROUP BY 1, 2
    UNION ALL SELECT w.user_id, n.user_id, k, row_number() OVER (PARTITION BY w.user_id ORDER BY {h(f"'{seed}'", "'full'", "w.user_id", "number")}, n.user_id)
    FROM {out}_w w CROSS JOIN {users} n WHERE w.user_id <> n.user_id AND 2 * k > (SELECT count(*) FROM {users})) WHERE rn <= k)"""


def bfs_sql(edges: str, depth: int, docs: str) -> str:
    """dist(doc_id, user_id, dist) by breadth-first steps from the holders over reversed edges."""
    out = [f"b0 AS MATERIALIZED (SELECT DISTINCT doc_id, user_id, 0 AS dist FROM train WHERE doc_id IN (SELECT doc_id FROM {docs}))"]
    for d in range(1, depth + 1):
        out.append(f"""b{d} AS MATERIALIZED (
  SELECT * FROM b{d - 1} UNION ALL SELECT DISTINCT f.doc_id, e.src, {d} FROM b{d - 1} f JOIN {edges} e ON e.dst = f.user_id
  WHERE f.dist = {d - 1} AND NOT EXISTS (SELECT 1 FROM b{d - 1} s WHERE s.doc_id = f.doc_id AND s.user_id = e.src))""")
    return ",\n".join(out)


def with_(*ctes: str) -> str:
    return "WITH " + ",\n".join(ctes) + "\n"
