"""The whole fit as SQL: sample, seeding, clustering, weights, strength and number of bins.

Each number of bins from the first value down to 2 is fitted (a database cannot stop early), by two
recursive queries: one row set per seeding round, one per clustering pass.
"""

from __future__ import annotations


def sample_sql(rows: str, keys: tuple[str, ...], cap: int, seed: int = 0) -> str:
    """(id, x, y): the rows of smallest MD5 of seed and keys, numbered from 1 in that order."""
    text = " || ':' || ".join([f"'{seed}'", *(f"{k}::VARCHAR" for k in keys)])
    return f"SELECT row_number() OVER (ORDER BY h, x, y) AS id, x, y FROM (SELECT md5({text}) AS h, x, y FROM {rows} ORDER BY h, x, y LIMIT {cap})"


_GAP = "((s.x - c.cx) * (s.x - c.cx) + (s.y - c.cy) * (s.y - c.cy))"

_BLOCKS = f"""blocks(k, round, id, x, y, taken) AS (
    SELECT k, -1::BIGINT, id, x, y, false FROM s, ks
    UNION ALL
    SELECT k, round + 1, id, x, y, row_number() OVER (PARTITION BY k ORDER BY CASE WHEN id = c_id THEN -1.0 ELSE {_GAP} END, id) <= n // k + CASE WHEN round + 1 < n % k THEN 1 ELSE 0 END
    FROM (SELECT s.*, c.id AS c_id, c.x AS cx, c.y AS cy FROM blocks s JOIN (
        SELECT k, id, x, y FROM (
            SELECT p.k, p.id, p.x, p.y, coalesce(min((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y)), 0) AS d
            FROM blocks p LEFT JOIN blocks q ON p.k = q.k AND p.id <> q.id AND NOT q.taken WHERE NOT p.taken GROUP BY ALL)
        QUALIFY row_number() OVER (PARTITION BY k ORDER BY d DESC, id) = 1) c ON s.k = c.k WHERE NOT s.taken) t, size)""".replace("s.x - c.cx", "x - cx").replace("s.y - c.cy", "y - cy")


def _lloyd(start: str, name: str = "lloyd", passes: int = 100) -> str:
    """Passes until the centroids move no more; the rows of a K's last pass are its centroids."""
    return f"""{name}(k, pass, bin, cx, cy, moved) AS (
    {start}
    UNION ALL
    SELECT k, pass + 1, bin, nx, ny, sum((nx - cx) * (nx - cx) + (ny - cy) * (ny - cy)) OVER (PARTITION BY k)
    FROM (SELECT c.*, coalesce(m.x, c.cx) AS nx, coalesce(m.y, c.cy) AS ny FROM {name} c
        LEFT JOIN (SELECT k, bin, avg(x) AS x, avg(y) AS y FROM (SELECT c.k, s.id, s.x, s.y, arg_min(c.bin, {_GAP}) AS bin FROM {name} c, s GROUP BY c.k, s.id, s.x, s.y) GROUP BY k, bin) m
        ON c.k = m.k AND c.bin = m.bin WHERE c.moved > 1e-6 AND c.pass < {passes}) t),
    {name}_end AS MATERIALIZED (SELECT k, bin, cx, cy FROM {name} QUALIFY pass = max(pass) OVER (PARTITION BY k))"""


_FROM_BLOCKS = "SELECT k, 0, round, avg(x), avg(y), 1e9 FROM blocks WHERE taken GROUP BY k, round"
_FROM_FIRST = "SELECT k, 0, id - 1, x, y, 1e9 FROM s, ks WHERE id <= k"


def fit_sql(rows: str, keys: tuple[str, ...], cap: int, tail: str, beta: int = 50, k_init: int | None = None, ratio: str = "relative", init: str = "greedy", feasible: str = "true", thetas: str = "SELECT round(i * 0.05::DOUBLE, 10) AS theta FROM range(31) t(i)") -> str:
    """WITH clauses of a fit, then `tail`. They end in tried(k, theta, low, sd, ok), one row per number of bins and strength, weights(k, theta, bin, cx, cy, w)
    and best(k, theta, low, sd): each K's first feasible strength."""
    expected = "(n // k + CASE WHEN bin < n % k THEN 1 ELSE 0 END)" if ratio == "relative" else "n"
    seeds, start = (_BLOCKS + ",", _FROM_BLOCKS) if init == "greedy" else ("", _FROM_FIRST)
    return f"""WITH RECURSIVE s AS MATERIALIZED ({sample_sql(rows, keys, cap)}),
    size AS MATERIALIZED (SELECT count(*) AS n FROM s),
    ks AS MATERIALIZED (SELECT unnest(range(2, least({k_init or f"n // {beta}"}, n) + 1)) AS k FROM size),
    {seeds} {_lloyd(start)},
    held AS (SELECT k, bin, count(*) AS n FROM (SELECT c.k, s.id, arg_min(c.bin, {_GAP}) AS bin FROM lloyd_end c, s GROUP BY c.k, s.id) GROUP BY k, bin),
    weights AS MATERIALIZED (SELECT c.k, theta, c.bin, cx, cy, exp(theta * (coalesce(h.n, 0) / e - 1)) AS w
        FROM (SELECT c.*, {expected} AS e FROM lloyd_end c, size) c LEFT JOIN held h ON c.k = h.k AND c.bin = h.bin, ({thetas})),
    counts AS (SELECT k, theta, bin, count(*) AS n FROM (SELECT c.k, c.theta, s.id, arg_min(c.bin, {_GAP} * (w * w)) AS bin FROM weights c, s GROUP BY c.k, c.theta, s.id) GROUP BY k, theta, bin),
    tried AS MATERIALIZED (SELECT k, theta, min(c.n) AS low, stddev_pop(c.n) AS sd, count(*) = k AND min(c.n) >= {beta} AND {feasible} AS ok FROM counts c GROUP BY k, theta),
    best AS (SELECT k, theta, low, sd FROM tried WHERE ok QUALIFY row_number() OVER (PARTITION BY k ORDER BY theta) = 1)
    {tail}"""


def whole(rows: str) -> str:
    """Tail: the chosen histogram, counted on all rows."""
    return f""", chosen AS MATERIALIZED (SELECT c.* FROM weights c JOIN (SELECT k, theta FROM best ORDER BY k DESC LIMIT 1) b ON c.k = b.k AND c.theta = b.theta),
    a AS (SELECT id, arg_min(c.bin, {_GAP} * (w * w)) AS bin FROM (SELECT row_number() OVER () AS id, x, y FROM {rows}) s, chosen c GROUP BY id),
    o AS (SELECT c.bin, count(a.id) AS n FROM chosen c LEFT JOIN a ON a.bin = c.bin GROUP BY c.bin)
    SELECT 'balanced' AS kind, (SELECT any_value(k) FROM chosen)::INTEGER AS n_bins, (SELECT any_value(theta) FROM chosen)::DOUBLE AS theta, min(n)::INTEGER AS min_count, sum(n)::INTEGER AS n_train FROM o"""


def fallback(rows: str, k: int) -> str:
    """Tail: nothing was feasible; k-means from the first rows of the sample, unit weights, counted on all rows."""
    start = f"SELECT {k}, 0, id - 1, x, y, 1e9 FROM s WHERE id <= {k} AND NOT EXISTS (SELECT 1 FROM best)"
    return f""", {_lloyd(start, "plain")},
    a AS (SELECT id, arg_min(c.bin, {_GAP}) AS bin FROM (SELECT row_number() OVER () AS id, x, y FROM {rows}) s, plain_end c GROUP BY id),
    o AS (SELECT c.bin, count(a.id) AS n FROM plain_end c LEFT JOIN a ON a.bin = c.bin GROUP BY c.bin)
    SELECT 'fallback' AS kind, count(*)::INTEGER AS n_bins, 0.0::DOUBLE AS theta, min(n)::INTEGER AS min_count, sum(n)::INTEGER AS n_train FROM o"""


def kmeans_test(rows: str, keys: tuple[str, ...], cap: int, train: str, test: str, beta: int = 50) -> str:
    """Plain k-means from the first rows of a sample of the training rows; `test` reads counted(o, t), the counts of all training and all other rows."""
    return f"""WITH RECURSIVE s AS MATERIALIZED ({sample_sql(f"(SELECT * FROM {rows} WHERE {train})", keys, cap)}),
    ks AS (SELECT greatest(count(*) // {beta}, 1) AS k FROM s),
    {_lloyd(_FROM_FIRST)},
    a AS (SELECT id, early, arg_min(c.bin, {_GAP}) AS bin FROM (SELECT row_number() OVER () AS id, {train} AS early, x, y FROM {rows}) s, lloyd_end c GROUP BY id, early),
    n AS (SELECT c.bin, count(*) FILTER (WHERE early) AS a, count(*) FILTER (WHERE NOT early) AS b FROM lloyd_end c LEFT JOIN a ON a.bin = c.bin GROUP BY c.bin),
    counted AS (SELECT list(a ORDER BY bin) AS o, list(b ORDER BY bin) AS t FROM n)
    SELECT * FROM ({test})"""


#: Tail: the strength by which each K's choice is made, for the largest feasible K and for the K that bisection finds.
ABLATIONS = """, last AS (SELECT * FROM tried WHERE ok AND theta = (SELECT max(theta) FROM tried)),
    evenest AS (SELECT * FROM tried WHERE ok QUALIFY row_number() OVER (PARTITION BY k ORDER BY round(sd, 9), theta) = 1),
    halve(lo, hi, hit) AS (
        SELECT 2::BIGINT, max(k)::BIGINT, NULL::BIGINT FROM ks
        UNION ALL
        SELECT CASE WHEN ok THEN mid + 1 ELSE lo END, CASE WHEN ok THEN hi ELSE mid - 1 END, CASE WHEN ok THEN mid ELSE hit END
        FROM (SELECT *, (lo + hi) // 2 AS mid, ((lo + hi) // 2) IN (SELECT k FROM best) AS ok FROM halve WHERE lo <= hi)),
    picked AS (SELECT 'no_rescale' AS variant, k, theta, low FROM tried WHERE ok AND theta = 0 QUALIFY k = max(k) OVER ()
        UNION ALL SELECT 'last', k, theta, low FROM last QUALIFY k = max(k) OVER ()
        UNION ALL SELECT 'best', k, theta, low FROM evenest QUALIFY k = max(k) OVER ()
        UNION ALL SELECT 'grid_nn', k, theta, low FROM best QUALIFY k = max(k) OVER ()
        UNION ALL SELECT 'bisect', k, theta, low FROM best WHERE k = (SELECT max(hit) FROM halve))
    SELECT variant, 'balanced' AS kind, k::INTEGER AS n_bins, theta::DOUBLE AS theta, low::INTEGER AS min_count FROM picked"""


def spanning_sql(points: str) -> str:
    """Edges of the spanning tree of (id, x, y), grown from the smallest id by the lightest edge out, ties by lower ids."""
    return f"""WITH RECURSIVE p AS MATERIALIZED ({points[1:-1]}),
    e AS MATERIALIZED (SELECT p.id AS a, q.id AS b, (p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y) AS d2 FROM p JOIN p q ON p.id < q.id),
    grown(held, a, b, d2) AS (
        SELECT [min(id)], NULL::BIGINT, NULL::BIGINT, NULL::DOUBLE FROM p
        UNION ALL
        SELECT * FROM (SELECT list_append(held, CASE WHEN list_contains(held, e.a) THEN e.b ELSE e.a END), e.a, e.b, e.d2 FROM grown g, e
            WHERE list_contains(held, e.a) <> list_contains(held, e.b) ORDER BY e.d2, e.a, e.b LIMIT 1) t)
    SELECT a, b, d2 FROM grown WHERE a IS NOT NULL"""
