"""Policies and partitionings as DuckDB SQL, for the oracles: the definitions said again in another language."""

from __future__ import annotations

from aclvec.functions.portable import draw_sql
from aclvec.operators.generators import WIDE

SEGMENTS = "CASE c_mktsegment WHEN 'AUTOMOBILE' THEN 100 WHEN 'BUILDING' THEN 101 WHEN 'FURNITURE' THEN 102 WHEN 'HOUSEHOLD' THEN 103 WHEN 'MACHINERY' THEN 104 END"

N1 = f"""docs AS (SELECT vec_id AS doc_id FROM embeddings),
users AS (SELECT c_custkey AS user_id FROM customer),
ua AS (SELECT c_custkey AS user_id, c_nationkey AS role_id FROM customer
  UNION ALL SELECT c_custkey, {SEGMENTS} FROM customer WHERE c_custkey % 3 = 0 AND {SEGMENTS} IS NOT NULL),
pa AS (SELECT DISTINCT role_id, doc_id FROM (
  SELECT n_nationkey AS role_id, vec_id AS doc_id FROM embeddings, nation WHERE vec_id % 25 = 0
  UNION ALL SELECT n_nationkey, vec_id FROM embeddings JOIN nation ON n_regionkey = vec_id % 25 - 1 WHERE vec_id % 25 BETWEEN 1 AND 5
  UNION ALL SELECT (label + 10 * (vec_id % 3)) % 25, vec_id FROM embeddings WHERE vec_id % 25 >= 6
  UNION ALL SELECT (label + 10 * (vec_id % 3) + 1) % 25, vec_id FROM embeddings WHERE vec_id % 25 >= 6 AND vec_id % 7 = 0
  UNION ALL SELECT 100 + label // 2, vec_id FROM embeddings WHERE vec_id % 25 >= 6 AND vec_id % 2 = 0))"""

N2 = """docs AS (SELECT p_partkey AS doc_id FROM part),
users AS (SELECT c_custkey AS user_id FROM customer),
ua AS (SELECT c_custkey AS user_id, c_nationkey AS role_id FROM customer),
pa AS (SELECT DISTINCT c_nationkey AS role_id, l_partkey AS doc_id FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey
  WHERE l_returnflag = 'R' AND l_quantity >= 40 AND l_discount >= 0.05 AND l_partkey IN (SELECT p_partkey FROM part))"""

N3 = """docs AS (SELECT doc_id FROM documents),
users AS (SELECT c_custkey AS user_id FROM customer),
ua AS (SELECT user_id, user_id % 20 AS role_id FROM users UNION ALL SELECT user_id, 100 + (user_id // 4) % 4 FROM users WHERE user_id % 4 = 0
  UNION ALL SELECT user_id, 200 FROM users WHERE user_id % 50 = 0 UNION ALL SELECT user_id, 201 FROM users WHERE user_id % 75 = 0),
pa AS (SELECT DISTINCT role_id, doc_id FROM (SELECT substr(source, 4)::INT AS role_id, doc_id FROM documents
  UNION ALL SELECT CASE lang WHEN 'de' THEN 100 WHEN 'en' THEN 101 WHEN 'es' THEN 102 WHEN 'fr' THEN 103 END, doc_id FROM documents WHERE lang IN ('de', 'en', 'es', 'fr')
  UNION ALL SELECT 200, doc_id FROM labels WHERE quality = 1 UNION ALL SELECT 201, doc_id FROM labels WHERE toxic = 1) WHERE doc_id IN (SELECT doc_id FROM documents))"""

H1 = """docs AS (SELECT i::BIGINT AS doc_id FROM range(1, 13) t(i)),
users AS (SELECT i::BIGINT AS user_id FROM range(1, 7) t(i)),
ua AS (SELECT user_id::BIGINT AS user_id, role_id FROM (VALUES (1, 1), (2, 2), (3, 3), (4, 4), (5, 1), (5, 3), (6, 3), (6, 4)) t(user_id, role_id)),
pa AS (SELECT 1 AS role_id, doc_id FROM docs WHERE doc_id <= 6 UNION ALL SELECT 2, doc_id FROM docs WHERE doc_id BETWEEN 5 AND 8
  UNION ALL SELECT 3, doc_id FROM docs WHERE doc_id BETWEEN 8 AND 10 UNION ALL SELECT 4, doc_id FROM docs WHERE doc_id BETWEEN 9 AND 11)"""

TABLED_H1 = """docs AS (SELECT p_partkey AS doc_id FROM part),
users AS (SELECT c_custkey AS user_id FROM customer),
ua AS (SELECT c_custkey AS user_id, role_id FROM customer JOIN (VALUES (1, 1), (2, 2), (3, 3), (4, 4), (5, 1), (5, 3), (6, 3), (6, 4)) t(u, role_id) ON u = c_custkey % 6 + 1),
pa AS (SELECT role_id, p_partkey AS doc_id FROM part JOIN (VALUES (1, 1, 6), (2, 5, 8), (3, 8, 10), (4, 9, 11)) t(role_id, low, high) ON p_partkey % 12 + 1 BETWEEN low AND high)"""


VECTORS, TEXTS = "SELECT vec_id AS doc_id FROM embeddings", "SELECT doc_id FROM documents"


def _docs(n_users: int, docs: str = VECTORS) -> str:
    return f"docs AS ({docs}), n AS (SELECT count(*) AS d FROM docs), users AS (SELECT i AS user_id FROM range({n_users}) t(i))"


def _drawn_docs(name: str, n_roles: int, m_p: str, dist: str, salt: int) -> str:
    m = m_p if dist == "full" else f"{draw_sql('r', salt, m_p)} + 1"
    x = "(r * 1000003 + i)"
    idx = f"({draw_sql(x, salt + 1, WIDE)} * {WIDE} + {draw_sql(x, salt + 2, WIDE)}) % d"
    return f"{name} AS (SELECT DISTINCT r::INT AS role_id, {idx} AS doc_id FROM (SELECT r, d, unnest(range(1, ({m})::BIGINT + 1)) AS i FROM range({n_roles}) t(r), n) WHERE {idx} IN (SELECT doc_id FROM docs))"


def _drawn_roles(name: str, source: str, key: str, n_roles: int, m_r: int, salt: int, out: str) -> str:
    return f"{name} AS (SELECT DISTINCT k AS {out.split()[0]}, {draw_sql('k * 1009 + i', salt + 1, n_roles)} AS {out.split()[1]} FROM (SELECT {key} AS k, unnest(range(1, {draw_sql(key, salt, m_r)} + 2)) AS i FROM {source}))"


def uniform(n_users: int, n_roles: int, m_r: int, factor: int, docs: str = VECTORS) -> str:
    return ",\n".join([_docs(n_users, docs), _drawn_docs("pa", n_roles, f"greatest(1, d * {factor} // {n_roles})", "uniform", 3), _drawn_roles("ua", "users", "user_id", n_roles, m_r, 13, "user_id role_id")])


def tree(n_users: int, n_roles: int, b0: int = 3, b1: int = 4, docs: str = VECTORS, bounds: list[float] | None = None) -> str:
    """The pool of roles ends before the height does, so the tree follows from running sums of the numbers of children."""
    block = f"doc_id * {n_roles} // d" if bounds is None else f"len(list_filter({bounds[:-1]}, lambda e: doc_id >= floor(e * d)))"
    return f"""{_docs(n_users, docs)},
kids AS (SELECT r, {b0} + {draw_sql('r', 21, b1 - b0 + 1)} AS c FROM range({n_roles}) t(r)),
starts AS (SELECT r, 1 + coalesce(sum(c) OVER (ORDER BY r ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS s FROM kids),
parent AS (SELECT t.r AS role_id, max(starts.r) AS parent_id FROM range(1, {n_roles}) t(r) JOIN starts ON s <= t.r GROUP BY t.r),
anc AS (SELECT * FROM (WITH RECURSIVE up AS (SELECT r AS role_id, r AS anc_id FROM range({n_roles}) t(r) UNION ALL SELECT up.role_id, parent.parent_id FROM up JOIN parent ON parent.role_id = up.anc_id) SELECT * FROM up)),
ua AS (SELECT user_id, 1 + user_id % ({n_roles} - 1) AS role_id FROM users),
pa AS (SELECT role_id, doc_id FROM docs, n, anc WHERE anc_id = {block})"""


def two_tier(n_users: int, n_fr: int, n_br: int, m_fr: int, m_br: int, divisor: int = 25, docs: str = VECTORS) -> str:
    return ",\n".join([_docs(n_users, docs), _drawn_docs("func_pa", n_fr, f"greatest(1, d // {divisor})", "full", 41), _drawn_roles("biz", f"range({n_br}) t(b)", "b", n_fr, m_fr, 31, "role_id func_id"),
        _drawn_roles("ua", "users", "user_id", n_br, m_br, 33, "user_id role_id"), "pa AS (SELECT DISTINCT biz.role_id, doc_id FROM biz JOIN func_pa ON func_pa.role_id = biz.func_id)"])


SETS = """user_sets AS (SELECT user_id, string_agg(role_id::VARCHAR, ',' ORDER BY role_id) AS rs FROM (SELECT DISTINCT user_id, role_id FROM ua) GROUP BY user_id),
sets AS (SELECT rs, count(*) AS n_users FROM user_sets GROUP BY rs),
set_role AS (SELECT DISTINCT rs, role_id FROM user_sets JOIN ua USING (user_id)),
flat AS (SELECT DISTINCT rs, doc_id FROM set_role JOIN pa USING (role_id))"""

PARTS = {
    "rls": "part_doc AS (SELECT 'all' AS part, doc_id FROM docs), route AS (SELECT rs, 'all' AS part FROM sets)",
    "role_part": "part_doc AS (SELECT DISTINCT role_id::VARCHAR AS part, doc_id FROM pa), route AS (SELECT rs, role_id::VARCHAR AS part FROM set_role)",
    "user_part": "part_doc AS (SELECT rs AS part, doc_id FROM flat), route AS (SELECT rs, rs AS part FROM sets)",
    "mod4": "part_doc AS (SELECT DISTINCT (role_id % 4)::VARCHAR AS part, doc_id FROM pa), route AS (SELECT DISTINCT rs, (role_id % 4)::VARCHAR AS part FROM set_role)",
}

MEASURED = """sizes AS (SELECT part, count(*) AS n_docs FROM part_doc GROUP BY part),
cost AS (SELECT part, n_docs, ln(greatest(n_docs, 2)) * (1.0 * 40.0 + 20.0) AS cost FROM sizes),
set_cost AS (SELECT rs, sum(cost) AS cost FROM route JOIN cost USING (part) GROUP BY rs),
sel AS (SELECT route.rs, route.part, count(flat.doc_id) AS permitted, any_value(n_docs) AS n_docs, count(flat.doc_id) / any_value(n_docs) AS s
  FROM route JOIN sizes USING (part) JOIN part_doc USING (part) LEFT JOIN flat ON flat.rs = route.rs AND flat.doc_id = part_doc.doc_id GROUP BY route.rs, route.part)"""


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n"


SMALL_UNI = {"n_users": 150, "n_roles": 20}
SMALL_TREE = {"n_users": 150, "n_roles": 25}
SMALL_TIER = {"n_users": 150, "n_fr": 10, "n_br": 20}

POLICIES = {
    "n1": N1, "n2": N2, "n3": N3, "h1": TABLED_H1, "hand": H1,
    "uni_a": uniform(**SMALL_UNI, m_r=2, factor=5), "uni_s": uniform(**SMALL_UNI, m_r=1, factor=9),
    "tree_a": tree(**SMALL_TREE),
    "tier_a": two_tier(**SMALL_TIER, m_fr=3, m_br=3), "tier_b": two_tier(**SMALL_TIER, m_fr=3, m_br=9), "tier_s": two_tier(**SMALL_TIER, m_fr=3, m_br=1),
}


def drawn(n: int) -> str:
    """drawn(query_id, user_id, q_vec_id): n vectors and n users in the order of the hash."""
    return f"""qv AS (SELECT row_number() OVER (ORDER BY h, vec_id) AS query_id, vec_id FROM (SELECT vec_id, {draw_sql('vec_id', 11, WIDE)} AS h FROM embeddings) QUALIFY query_id <= {n}),
qu AS (SELECT row_number() OVER (ORDER BY h, user_id) AS query_id, user_id FROM (SELECT user_id, {draw_sql('user_id', 13, WIDE)} AS h FROM users) QUALIFY query_id <= {n}),
drawn AS (SELECT query_id, user_id, vec_id AS q_vec_id FROM qv JOIN qu USING (query_id))"""


def distances() -> str:
    """queries(query_id, user_id, qvec): vectors whose id is divisible by 20; dist(query_id, doc_id, d) of all vectors."""
    return f"""queries AS (SELECT vec_id AS query_id, (SELECT min(c_custkey) FROM customer) + {draw_sql('vec_id', 13, WIDE)} % (SELECT count(*) FROM customer) AS user_id, embedding AS qvec FROM embeddings WHERE vec_id % 20 = 0),
dist AS (SELECT query_id, vec_id AS doc_id, list_sum(list_transform(range(1, len(qvec) + 1), lambda i: (embedding[i]::DOUBLE - qvec[i]::DOUBLE) * (embedding[i]::DOUBLE - qvec[i]::DOUBLE))) AS d FROM embeddings, queries)"""


TRUTH = """allowed AS (SELECT DISTINCT query_id, doc_id FROM queries JOIN ua USING (user_id) JOIN pa USING (role_id)),
truth AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY round(d, 6), doc_id) AS rank, doc_id, round(d, 6) AS dist FROM dist SEMI JOIN allowed USING (query_id, doc_id) QUALIFY rank <= 10)"""
