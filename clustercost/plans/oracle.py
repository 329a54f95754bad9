"""DuckDB SQL that states the same results independently: sequential folds in rank order, brute-force counts."""

from __future__ import annotations

import re

#: Pairs of each graph, as ``nodes(id)`` and ``pairs(u, v)``.
_COSINE = """nodes AS MATERIALIZED (SELECT vec_id AS id FROM embeddings),
vec AS MATERIALIZED (SELECT vec_id AS id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
scored AS MATERIALIZED (SELECT a.id AS u, b.id AS v, list_cosine_similarity(a.e, b.e) AS score FROM vec a JOIN vec b ON a.id < b.id),
pairs AS MATERIALIZED (SELECT u, v FROM scored WHERE score > {theta})"""
_PAGE = """nodes AS MATERIALIZED (SELECT page_id AS id FROM pages),
target AS MATERIALIZED (SELECT DISTINCT page_id AS id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS t FROM pages),
pairs AS MATERIALIZED (SELECT a.id AS u, b.id AS v FROM target a JOIN target b ON a.t = b.t AND a.id < b.id GROUP BY ALL HAVING count(*) >= {least})"""
_PART = """nodes AS MATERIALIZED (SELECT p_partkey AS id FROM part),
bought AS MATERIALIZED (SELECT DISTINCT l_orderkey AS o, l_partkey AS id FROM lineitem),
pairs AS MATERIALIZED (SELECT a.id AS u, b.id AS v FROM bought a JOIN bought b ON a.o = b.o AND a.id < b.id GROUP BY ALL HAVING count(*) >= 2)"""
_DOC = """nodes AS MATERIALIZED (SELECT doc_id AS id FROM documents),
wl AS MATERIALIZED (SELECT doc_id AS id, string_split(lower(text), ' ') AS w FROM documents WHERE text IS NOT NULL),
sh AS MATERIALIZED (SELECT DISTINCT id, array_to_string(w[i:i + 3], ' ') AS s FROM (SELECT id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM wl)),
cnt AS MATERIALIZED (SELECT id, count(*) AS c FROM sh GROUP BY id),
met AS MATERIALIZED (SELECT a.id AS u, b.id AS v, count(*) AS c FROM sh a JOIN sh b ON a.s = b.s AND a.id < b.id GROUP BY ALL),
scored AS MATERIALIZED (SELECT m.u, m.v, m.c / (x.c + y.c - m.c) AS score FROM met m JOIN cnt x ON x.id = m.u JOIN cnt y ON y.id = m.v),
pairs AS MATERIALIZED (SELECT u, v FROM scored WHERE score > {theta})"""
_CUST = """nodes AS MATERIALIZED (SELECT c_custkey AS id FROM customer),
pairs AS MATERIALIZED (SELECT a.c_custkey AS u, b.c_custkey AS v FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_mktsegment = b.c_mktsegment AND a.c_custkey < b.c_custkey)"""
_EVT = """nodes AS MATERIALIZED (SELECT event_id AS id FROM events),
pairs AS MATERIALIZED (SELECT a.event_id AS u, b.event_id AS v FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000)"""
GRAPH = {
    "emb": _COSINE.format(theta=0.2),
    "emb3": _COSINE.format(theta=0.3),
    "page": _PAGE.format(least=1),
    "page2": _PAGE.format(least=2),
    "part": _PART,
    "doc": _DOC.format(theta=0.05),
    "doc2": _DOC.format(theta=0.2),
    "cust": _CUST,
    "evt": _EVT,
}

#: Orders and sequential folds over ``trials(trial, seed, k, ...)``; calls are not capped.
FOLD = """ranked AS MATERIALIZED (SELECT t.trial, n.id, md5(t.seed || ':' || n.id) AS key, row_number() OVER (PARTITION BY t.trial ORDER BY md5(t.seed || ':' || n.id), n.id) AS rk FROM nodes n, trials t),
oriented AS MATERIALIZED (SELECT a.trial, greatest(a.rk, b.rk) AS rk, least(a.rk, b.rk) AS near FROM {fold_pairs} p JOIN ranked a ON a.id = p.u{a_trial} JOIN ranked b ON b.id = p.v AND b.trial = a.trial),
near AS MATERIALIZED (SELECT trial, rk, list(near ORDER BY near) AS e FROM oriented GROUP BY ALL),
steps AS MATERIALIZED (SELECT r.trial, r.rk, coalesce(near.e, []) AS e FROM ranked r LEFT JOIN near USING (trial, rk)),
fold AS (SELECT trial, 0::BIGINT AS i, []::BIGINT[] AS piv, []::BIGINT[] AS calls FROM trials
         UNION ALL SELECT f.trial, f.i + 1, list_append(f.piv, coalesce(list_filter(s.e, lambda j: f.piv[j] = j)[1], f.i + 1)),
                list_append(f.calls, 1 + coalesce(list_sum(list_transform(s.e[1:coalesce(list_position(list_transform(s.e, lambda j: f.piv[j] = j), true), len(s.e))], lambda j: f.calls[j])), 0)::BIGINT)
         FROM fold f JOIN steps s ON s.trial = f.trial AND s.rk = f.i + 1),
last AS MATERIALIZED (SELECT f.trial, f.piv, f.calls FROM fold f WHERE f.i = (SELECT count(*) FROM nodes)),
exact AS MATERIALIZED (SELECT r.trial, r.id, r.rk, r.key, q.id AS pivot, l.calls[r.rk] AS calls FROM ranked r JOIN last l USING (trial) JOIN ranked q ON q.trial = r.trial AND q.rk = l.piv[r.rk])"""


def fold(trial_pairs: bool = False) -> str:
    """``exact(trial, id, rk, key, pivot, calls)``; with ``trial_pairs`` from ``tpairs(trial, u, v)``."""
    return FOLD.format(fold_pairs="tpairs" if trial_pairs else "pairs", a_trial=" AND a.trial = p.trial" if trial_pairs else "")


BUDGETED = """labels AS MATERIALIZED (SELECT e.trial, e.id, CASE WHEN e.calls <= t.k THEN e.pivot ELSE e.id END AS pivot, least(e.calls, t.k + 1) AS calls, e.calls > t.k AS timed_out FROM exact e JOIN trials t USING (trial))"""


def costs(labels: str, name: str, trial_pairs: bool = False) -> str:
    """``name(trial, n, m, kept, together, cost)`` of a label table."""
    source, on = ("tpairs", " AND a.trial = p.trial") if trial_pairs else ("pairs", "")
    return f"""{name} AS MATERIALIZED (
  SELECT s.trial, s.n, coalesce(i.m, 0) AS m, coalesce(i.kept, 0) AS kept, s.together, coalesce(i.m, 0) + s.together - 2 * coalesce(i.kept, 0) AS cost
  FROM (SELECT trial, sum(c)::BIGINT AS n, sum(c * (c - 1) // 2)::BIGINT AS together FROM (SELECT trial, pivot, count(*) AS c FROM {labels} GROUP BY ALL) GROUP BY trial) s
  LEFT JOIN (SELECT a.trial, count(*) AS m, count(*) FILTER (a.pivot = b.pivot) AS kept FROM {source} p JOIN {labels} a ON a.id = p.u{on} JOIN {labels} b ON b.id = p.v AND b.trial = a.trial GROUP BY a.trial) i USING (trial))"""


#: ``al(trial, id, pivot, part)``: anchored lookups, from the exact fold: an anchor's calls and pivot status are final.
ANCHORED = """seen AS MATERIALIZED (SELECT o.trial, o.rk, o.near, x.calls, x.pivot = x.id AS is_pivot FROM oriented o JOIN trials t USING (trial) JOIN exact x ON x.trial = o.trial AND x.rk = o.near WHERE o.near <= t.r),
walk AS MATERIALIZED (SELECT trial, rk, min(near) FILTER (is_pivot) AS first FROM seen GROUP BY ALL),
spent AS MATERIALIZED (SELECT s.trial, s.rk, 1 + sum(s.calls) FILTER (w.first IS NULL OR s.near <= w.first) AS calls, any_value(w.first) AS first FROM seen s JOIN walk w USING (trial, rk) GROUP BY ALL),
al AS MATERIALIZED (
  SELECT r.trial, r.id, CASE WHEN coalesce(s.calls, 1) > t.k THEN r.id WHEN s.first IS NOT NULL THEN q.id WHEN r.rk <= t.r THEN r.id END AS pivot,
         CASE WHEN coalesce(s.calls, 1) > t.k OR s.first IS NOT NULL OR r.rk <= t.r THEN 'A' ELSE 'B' END AS part, least(coalesce(s.calls, 1), t.k + 1) AS calls
  FROM ranked r JOIN trials t USING (trial) LEFT JOIN spent s USING (trial, rk) LEFT JOIN ranked q ON q.trial = r.trial AND q.rk = s.first)"""


def _sample(name: str, source: str, size: str, salt: str) -> str:
    return f"""{name} AS MATERIALIZED (SELECT trial, id, pivot FROM (SELECT x.*, row_number() OVER (PARTITION BY x.trial ORDER BY md5('{salt}:' || t.seed || ':' || x.id), x.id) AS place, t.{size} AS wanted FROM {source} x JOIN trials t USING (trial)) WHERE place <= wanted)"""


#: Anchored mismatches by the four cases, pair by pair, without any counting trick.
AMISMATCH = """amis AS MATERIALIZED (
  SELECT a.trial, a.id AS x, b.id AS y FROM al a JOIN al b ON a.trial = b.trial AND a.id <> b.id
  LEFT JOIN pairs p ON p.u = least(a.id, b.id) AND p.v = greatest(a.id, b.id)
  WHERE CASE WHEN a.pivot IS NULL AND b.pivot IS NULL THEN false WHEN a.pivot IS NULL OR b.pivot IS NULL THEN p.u IS NOT NULL WHEN p.u IS NOT NULL THEN a.pivot <> b.pivot ELSE a.pivot = b.pivot END)"""


def hits(name: str, sample: str) -> str:
    return f"{name} AS MATERIALIZED (SELECT a.trial, a.id, count(s.id) AS hits FROM al a LEFT JOIN amis m ON m.trial = a.trial AND m.x = a.id LEFT JOIN {sample} s ON s.trial = m.trial AND s.id = m.y GROUP BY ALL)"


def part_a(mode: str) -> str:
    """``ea(trial, m_a, n, n_low, t1, t2)`` in one of the three modes."""
    limit = "greatest(t.cutoff, 4)" if mode == "floor" else "t.cutoff"
    counted = "h2.hits" if mode == "two_sample" else "h1.hits"
    second = [_sample("s1b", "al", "t1", "s1b"), hits("h2", "s1b")] if mode == "two_sample" else []
    join = "JOIN h2 USING (trial, id)" if mode == "two_sample" else ""
    return ",\n".join(
        [
            AMISMATCH,
            _sample("s1", "al", "t1", "s1"),
            hits("h1", "s1"),
            *second,
            f"cls AS MATERIALIZED (SELECT a.trial, a.id, a.pivot, h1.hits, h1.hits >= {limit} AND h1.hits > 0 AS is_high, {counted} AS eh FROM al a JOIN h1 USING (trial, id) {join} JOIN trials t USING (trial))",
            "low AS MATERIALIZED (SELECT trial, id, pivot FROM cls WHERE NOT is_high)",
            _sample("s2", "low", "t2", "s2"),
            "d2 AS MATERIALIZED (SELECT s.trial, count(m.y) AS d, count(DISTINCT s.id) AS drawn FROM s2 s LEFT JOIN amis m ON m.trial = s.trial AND m.x = s.id GROUP BY ALL)",
            "ea AS MATERIALIZED (SELECT c.trial, (coalesce(c.n * c.high / least(t.t1, c.n), 0) + coalesce(c.n_low * d2.d / d2.drawn, 0)) / 2 AS m_a, c.n, c.n_low, least(t.t1, c.n)::BIGINT AS t1, coalesce(d2.drawn, 0)::BIGINT AS t2 FROM (SELECT trial, count(*) AS n, count(*) FILTER (NOT is_high) AS n_low, coalesce(sum(eh) FILTER (is_high), 0) AS high FROM cls GROUP BY trial) c JOIN trials t USING (trial) LEFT JOIN d2 USING (trial))",
        ]
    )


#: ``eb(trial, m_b, n_b, t)``: residual mismatches counted pair by pair around sampled centers.
PART_B = ",\n".join(
    [
        "res AS MATERIALIZED (SELECT trial, id, pivot FROM al WHERE pivot IS NULL)",
        _sample("sb", "res", "t", "sb"),
        "clu AS MATERIALIZED (SELECT s.trial, s.id AS center, l.id AS member FROM sb s JOIN labels l ON l.trial = s.trial AND l.pivot = s.id)",
        "inn AS MATERIALIZED (SELECT a.trial, a.center, count(*) AS n_in FROM clu a JOIN clu b ON a.trial = b.trial AND a.center = b.center AND a.member < b.member LEFT JOIN pairs p ON p.u = a.member AND p.v = b.member WHERE p.u IS NULL GROUP BY ALL)",
        "sym AS MATERIALIZED (SELECT u AS x, v AS y FROM pairs UNION ALL SELECT v, u FROM pairs)",
        "outs AS MATERIALIZED (SELECT c.trial, c.center, count(*) AS n_out FROM clu c JOIN sym ON sym.x = c.member JOIN res r ON r.trial = c.trial AND r.id = sym.y LEFT JOIN clu o ON o.trial = c.trial AND o.center = c.center AND o.member = sym.y WHERE o.member IS NULL GROUP BY ALL)",
        "cen AS MATERIALIZED (SELECT c.trial, c.center, count(*) AS size, coalesce(any_value(i.n_in), 0) AS n_in, coalesce(any_value(o.n_out), 0) AS n_out FROM clu c LEFT JOIN inn i USING (trial, center) LEFT JOIN outs o USING (trial, center) GROUP BY ALL)",
        "eb AS MATERIALIZED (SELECT t.trial, coalesce(b.n_b * s.x / least(t.t, b.n_b), 0) AS m_b, b.n_b, least(t.t, b.n_b)::BIGINT AS t FROM trials t JOIN (SELECT trial, count(*) FILTER (pivot IS NULL) AS n_b FROM al GROUP BY trial) b USING (trial) LEFT JOIN (SELECT trial, sum(n_in + n_out / 2) AS x FROM cen GROUP BY trial) s USING (trial))",
    ]
)


def drawn(salt: str, q: str = "q") -> str:
    """``dp(trial, u, v)``: distinct hashed pairs over rank places, as many as the column ``q`` of trials tells."""
    return f"""num AS MATERIALIZED (SELECT trial, q, p, min(j) AS j FROM (SELECT t.trial, least(t.{q}, c.n * (c.n - 1) // 2) AS q, j, ('0x' || substr(md5('{salt}:' || t.seed || ':' || j), 1, 12))::BIGINT % (c.n * (c.n - 1) // 2) AS p
  FROM trials t, (SELECT count(*) AS n FROM nodes) c, unnest(range(0, 1000000)) g(j) WHERE j <= 2 * least(t.{q}, c.n * (c.n - 1) // 2) + 20) GROUP BY ALL),
kept AS MATERIALIZED (SELECT trial, p FROM (SELECT *, row_number() OVER (PARTITION BY trial ORDER BY j) AS o FROM num) WHERE o <= q),
tri AS MATERIALIZED (SELECT h, h * (h - 1) // 2 AS low FROM (SELECT unnest(range(1, (SELECT count(*) FROM nodes))) AS h)),
dp AS MATERIALIZED (SELECT k.trial, least(a.id, b.id) AS u, greatest(a.id, b.id) AS v FROM kept k JOIN tri ON k.p >= tri.low AND k.p < tri.low + tri.h JOIN ranked a ON a.trial = k.trial AND a.rk = tri.h + 1 JOIN ranked b ON b.trial = k.trial AND b.rk = k.p - tri.low + 1)"""


def pair_estimate(labels: str, name: str = "pe") -> str:
    return f"""{name} AS MATERIALIZED (SELECT d.trial, count(*) FILTER ((p.u IS NOT NULL) = (a.pivot <> b.pivot)) * ((SELECT count(*) FROM nodes) * ((SELECT count(*) FROM nodes) - 1) // 2) / count(*) AS estimate, count(*) AS q
  FROM dp d JOIN {labels} a ON a.trial = d.trial AND a.id = d.u JOIN {labels} b ON b.trial = d.trial AND b.id = d.v LEFT JOIN pairs p ON p.u = d.u AND p.v = d.v GROUP BY d.trial)"""


def trials(rows: list[tuple[str, int, float]], split: tuple[float, float, float, float] = (1 / 2, 1 / 8, 1 / 8, 1 / 8), fixed: int | None = None) -> str:
    """``trials(trial, seed, k, space, r, t1, t2, t, cutoff, q, qp)`` from (seed, k, space), or with all sizes fixed."""
    shown = ", ".join(f"({i}, '{seed}', {k}, {space!r}::DOUBLE)" for i, (seed, k, space) in enumerate(rows))
    size = (lambda s: str(fixed)) if fixed else (lambda s: f"least(n, greatest(1, floor(n * space * {s!r}::DOUBLE + 0.5)))::BIGINT")
    sizes = ", ".join(f"{size(s)} AS {name}" for s, name in zip(split, ("r", "t1", "t2", "t"), strict=True))
    return f"""trials AS MATERIALIZED (SELECT *, 2 * t1 / pow(n, 0.75) AS cutoff, greatest(1, floor(n * space / 2 + 0.5))::BIGINT AS q, greatest(1, floor((n * space - r) / 2 + 0.5))::BIGINT AS qp
  FROM (SELECT trial, seed, k, space, n, {sizes} FROM (VALUES {shown}) v(trial, seed, k, space), (SELECT count(*) AS n FROM nodes) c))"""


def query(*parts: str) -> str:
    """All but the last part are CTEs; the column name pivot is a keyword there and gets quoted."""
    text = "WITH RECURSIVE " + ",\n".join(x for x in parts[:-1] if x) + "\n" + parts[-1]
    return re.sub(r"""(?<![.\w"'])pivot(?![\w"'])""", '"pivot"', text)
