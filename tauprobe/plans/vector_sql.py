"""DuckDB SQL for the vector queries: common table expressions that derive a workload, its index and its outcomes.

The SQL takes another way than the engine: all pairs are scored, partitions are looked up, and the stopping rule is
evaluated with window functions, so agreement is a check of both.
"""

from __future__ import annotations

_WORDS = "list_filter(regexp_split_to_array(coalesce(t, ''), '[ \\t\\r\\n]+'), lambda w: w <> '')"
_PAIRS = "CASE WHEN len(ws) > 1 THEN list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) ELSE ws END"


def vectors(source: str, pairs: bool = False, plant: bool = False) -> str:
    """CTEs up to v(id, vec, n2)."""
    if source == "embeddings":
        more = ""
        if plant:
            more = " UNION ALL SELECT id + 1000000, list_transform(vec, lambda x, i: CASE WHEN i - 1 = id % 64 THEN x + 0.05 * (1 + id % 3) ELSE x END) FROM v0 WHERE id % 10 = 0"
        return f"""v0 AS (SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS vec FROM embeddings),
v AS (SELECT id, vec, list_dot_product(vec, vec) AS n2 FROM (SELECT id, vec FROM v0{more}))"""
    text = {
        "documents": "SELECT doc_id AS id, text AS t FROM documents",
        "pages": "SELECT page_id AS id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS t FROM pages",
        "conversations": "SELECT conv_id * 1000 + turn AS id, text AS t FROM conversations",
    }[source]
    return f"""texts AS ({text}),
split_ AS (SELECT id, {_WORDS} AS ws FROM texts),
toks AS (SELECT id, unnest({_PAIRS if pairs else 'ws'}) AS w FROM split_),
hashed AS (SELECT id, ('0x' || substr(md5(w), 1, 8))::BIGINT AS h FROM toks),
cells AS (SELECT id, h % 64 AS b, sum(CASE WHEN (h // 64) % 2 = 0 THEN -1 ELSE 1 END) AS c FROM hashed GROUP BY ALL HAVING sum(CASE WHEN (h // 64) % 2 = 0 THEN -1 ELSE 1 END) <> 0),
ids_ AS (SELECT DISTINCT id FROM cells), dims AS (SELECT unnest(range(0, 64)) AS b),
dense AS (SELECT id, list(CAST(coalesce(c, 0) AS DOUBLE) ORDER BY b) AS vec FROM (ids_ CROSS JOIN dims) LEFT JOIN cells USING (id, b) GROUP BY id),
v AS (SELECT id, vec, list_dot_product(vec, vec) AS n2 FROM dense)"""


def sim(a: str, b: str) -> str:
    return f"list_dot_product({a}.vec, {b}.vec) / sqrt({a}.n2 * {b}.n2)"


def index(source: str, pairs: bool = False, seed_every: int = 25, plant: bool = False, everything: bool = False, rounds: int = 0, only: str = "true") -> str:
    """CTEs up to base, qs, c(pid, vec, n2), assigned(id, pid). With `everything` all rows are queries; `only` restricts the rows."""
    held = "SELECT * FROM base" if everything else "SELECT * FROM base WHERE id % 50 = 0"
    near = lambda c: f"SELECT base.id, {c}.pid FROM base, {c} QUALIFY row_number() OVER (PARTITION BY base.id ORDER BY round({sim('base', c)}, 9) DESC, {c}.pid) = 1"
    seeds = f"SELECT row_number() OVER (ORDER BY id) - 1 AS pid, vec, n2 FROM base WHERE id % (SELECT greatest({seed_every}, CAST(round_even(sqrt(count(*)) / 4, 0) AS BIGINT)) FROM v) = 0"
    if rounds:
        lists = f"s0 AS MATERIALIZED ({seeds}), a0 AS MATERIALIZED ({near('s0')}), {moved('a0', 's0')}, c AS MATERIALIZED (SELECT * FROM moved)"
    else:
        lists = f"c AS MATERIALIZED ({seeds})"
    return f"""{vectors(source, pairs, plant)},
base AS MATERIALIZED (SELECT * FROM v WHERE {only}), qs AS MATERIALIZED ({held}),
{lists},
assigned AS MATERIALIZED ({near('c')})"""


def moved(assigned: str, centroids: str) -> str:
    """CTE moved(pid, vec, n2): unit means of the assigned rows' unit vectors; a centroid without rows stays."""
    return f"""unit_ AS (SELECT a.pid, list_transform(b.vec, lambda x: x / sqrt(b.n2)) AS u FROM {assigned} a JOIN base b ON a.id = b.id),
sums AS (SELECT pid, d, sum(u[d]) AS s FROM unit_, (SELECT unnest(range(1, 65)) AS d) GROUP BY pid, d),
means AS (SELECT pid, list(s ORDER BY d) AS vec FROM sums GROUP BY pid),
moved AS MATERIALIZED (SELECT pid, vec, list_dot_product(vec, vec) AS n2 FROM (SELECT z.pid, coalesce(m.vec, z.vec) AS vec FROM {centroids} z LEFT JOIN means m USING (pid)))"""


def probed(source: str, tau: float, p: int | None = 90, pairs: bool = False, same: str = "true", **kw) -> str:
    """CTEs up to probe(query_id, rank, pid), met(query_id, vec_id, sim, rank), outcome(query_id, rank, pid, n_hits), lists(p); `same` is a condition on query_id and vec_id."""
    limit = "" if p is None else f" WHERE rank <= {p}"
    return f"""{index(source, pairs, **kw)},
ranked AS (SELECT qs.id AS query_id, c.pid, row_number() OVER (PARTITION BY qs.id ORDER BY round({sim('qs', 'c')}, 9) DESC, c.pid) AS rank FROM qs, c),
probe AS MATERIALIZED (SELECT * FROM ranked{limit}),
lists AS (SELECT max(rank) AS p FROM probe),
scored AS MATERIALIZED (SELECT qs.id AS query_id, base.id AS vec_id, round({sim('qs', 'base')}, 12) AS sim FROM qs, base WHERE qs.id <> base.id),
met AS MATERIALIZED (SELECT s.query_id, s.vec_id, s.sim, p.rank FROM scored s JOIN assigned a ON a.id = s.vec_id JOIN probe p ON p.query_id = s.query_id AND p.pid = a.pid WHERE s.sim >= {tau} AND {same}),
outcome AS MATERIALIZED (SELECT p.query_id, p.rank, p.pid, count(m.vec_id) AS n_hits FROM probe p LEFT JOIN met m ON m.query_id = p.query_id AND m.rank = p.rank GROUP BY ALL)"""


def stops(windows: str) -> str:
    """CTE stop(query_id, w, stop): the first rank at which w ranks in a row were empty, else the last; windows as SQL list."""
    return f"""grid AS (SELECT unnest({windows}) AS w),
quiet AS MATERIALIZED (SELECT query_id, rank, n_hits, rank - coalesce(max(CASE WHEN n_hits > 0 THEN rank END) OVER (PARTITION BY query_id ORDER BY rank), 0) AS stale FROM outcome),
stop AS MATERIALIZED (SELECT query_id, w, coalesce(min(rank) FILTER (stale >= w), max(rank)) AS stop FROM quiet, grid GROUP BY ALL)"""


def top(source: str, k: int, where: str = "true", extra: str = "") -> str:
    """CTE text of edges(query_id, vec_id, sim, pos) from rows (query_id, vec_id, sim)."""
    part = f"{extra}query_id"
    return f"SELECT * FROM (SELECT {extra}query_id, vec_id, sim, row_number() OVER (PARTITION BY {part} ORDER BY sim DESC, vec_id) AS pos FROM {source} WHERE {where}) WHERE pos <= {k}"


TRUTH = "truth AS MATERIALIZED ({top})"


def truth(k: int = 10, tau: float = -2.0) -> str:
    """CTE truth: exact top k of each query at tau."""
    return f"truth AS MATERIALIZED ({top('scored', k, f'sim >= {tau}')})"


EDGES = "SELECT query_id, vec_id, round(sim, 6) AS sim, pos FROM ({})"
