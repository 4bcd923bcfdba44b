"""Partitions of the table as SQL: the definitions of blocks, sub-blocks, owners and messages once more, from numbers only.

Written from the definitions and not from ``geometry``, so each can test the other; DuckDB and Spark SQL users
can join these rows with their own.
"""

from __future__ import annotations


def cuts_ctes(n: int | str, p: int, k: int) -> str:
    """CTEs par (f, h, theta, n) and cuts (l, i, s, e): half-open interval i of 0..n at every level, nested halves.

    ``n`` is a number or a scalar subquery.
    """
    return f"""par AS (SELECT f, (f + 1) // 2 AS h, (n + f) // f AS theta, n FROM (SELECT ceil(sqrt(2 * {p}))::BIGINT AS f), (SELECT {n}::BIGINT AS n)),
cuts AS (SELECT 0 AS l, i, least(i * theta, n + 1) AS s, least((i + 1) * theta, n + 1) AS e FROM par, (SELECT unnest(range(0, 4096)) AS i) WHERE i < f
 UNION ALL
 SELECT l + 1, 2 * i + c, CASE WHEN c = 0 THEN s ELSE least(s + half, e) END, CASE WHEN c = 0 THEN least(s + half, e) ELSE e END
 FROM (SELECT cuts.*, c, (theta + (1 << (l + 1)::INT) - 1) // (1 << (l + 1)::INT) AS half FROM cuts, par, (VALUES (0), (1)) v(c) WHERE l < {k}))"""


def blocks_ctes(n: int | str, p: int, k: int, cut_levels: int | None = None) -> str:
    """CTEs from cuts (down to level ``cut_levels``) to blk (block_id, round, level, r0, r1, c0, c1, a, b).

    Level l has the intervals' pairs from the first diagonal that the level above left, f 2^(l-1) - h, up to its own.
    """
    return f"""{cuts_ctes(n, p, k if cut_levels is None else cut_levels)},
pairs AS (SELECT x.l, x.i AS a, y.i AS b, y.i - x.i AS t, x.s AS r0, x.e AS r1, y.s AS c0, y.e AS c1 FROM cuts x JOIN cuts y ON x.l = y.l AND x.i <= y.i, par
 WHERE x.l <= {k} AND (x.l = 0 OR (y.i >> 1) - (x.i >> 1) >= f * (1 << greatest(x.l - 1, 0)::INT) - h) AND (x.l = {k} OR y.i - x.i < f * (1 << x.l::INT) - h)),
blk AS (SELECT row_number() OVER (ORDER BY l, t, a) - 1 AS block_id, round, l AS level, r0, r1 - 1 AS r1, c0, c1 - 1 AS c1, a, b
 FROM (SELECT *, dense_rank() OVER (ORDER BY l, t) AS round FROM pairs) WHERE r1 > r0 AND c1 > c0)"""


def parts_ctes(n: int | str, p: int, k: int) -> str:
    """CTEs from cuts to prt (part_id, block_id, round, part, r0, r1, c0, c1): quarters of blocks below level k."""
    return f"""{blocks_ctes(n, p, k, k + 1)},
halves AS (SELECT l, i >> 1 AS i, s, e - 1 AS e, row_number() OVER (PARTITION BY l, i >> 1 ORDER BY i) - 1 AS nth, count(*) OVER (PARTITION BY l, i >> 1) AS of FROM cuts WHERE e > s),
prt AS (SELECT row_number() OVER (ORDER BY block_id, cn, rn DESC) - 1 AS part_id, * FROM (
 SELECT block_id, round, 'all' AS part, r0, r1, c0, c1, 0 AS cn, 0 AS rn FROM blk WHERE level = {k}
 UNION ALL
 SELECT block_id, round, CASE WHEN c.nth = 0 AND c.of > 1 THEN 'L' ELSE 'R' END || CASE WHEN r.nth = 0 THEN 'U' ELSE 'L' END, r.s, r.e, c.s, c.e, c.nth, r.nth
 FROM blk JOIN halves r ON r.l = level + 1 AND r.i = a JOIN halves c ON c.l = level + 1 AND c.i = b WHERE level < {k} AND c.e >= r.s))"""


_INTS = "block_id::INT AS block_id, round::INT AS round"
_BOX = "r0::INT AS r0, r1::INT AS r1, c0::INT AS c0, c1::INT AS c1"


def blocks_sql(n: int, p: int, k: int) -> str:
    return f"WITH RECURSIVE {blocks_ctes(n, p, k)} SELECT {_INTS}, level::INT AS level, {_BOX} FROM blk"


def parts_sql(n: int, p: int, k: int) -> str:
    return f"WITH RECURSIVE {parts_ctes(n, p, k)} SELECT part_id::INT AS part_id, {_INTS}, part, {_BOX} FROM prt"


def owners_cte(p: int) -> str:
    """CTE own (block_id, owner): the cyclic deal in the order of rounds."""
    return f"own AS (SELECT block_id, (row_number() OVER (ORDER BY round, r0) - 1) % {p} AS owner FROM blk)"


#: Whether block or part ``x`` reads cells of ``y``: the same rows further left, or the same columns further down.
DEPENDS = "(x.r0 <> y.r0 OR x.c0 <> y.c0 OR x.r1 <> y.r1 OR x.c1 <> y.c1) AND (y.r0 <= x.r1 AND x.r0 <= y.r1 AND y.c1 <= x.c1 AND y.c0 <= x.c0 OR y.c0 <= x.c1 AND x.c0 <= y.c1 AND y.r0 >= x.r0 AND y.r1 >= x.r1)"


def messages_sql(n: int, p: int, k: int, select: str = "SELECT DISTINCT block_id::INT AS block_id, step::INT AS step, parts, dst_owner::INT AS dst_owner FROM sent") -> str:
    """Pairs of parts and the workers that they go to: (block_id, step, parts, dst_owner) as CTE ``sent``."""
    return f"""WITH RECURSIVE {parts_ctes(n, p, k)}, {owners_cte(p)},
ends AS (SELECT l, i, min(s) FILTER (nth = 0) AS s0, min(e) FILTER (nth = 0) AS e0, max(s) AS s1, max(e) AS e1 FROM halves GROUP BY l, i),
pair AS (SELECT block_id, round, r0, c1, 4 AS step, 'all' AS parts, r0 AS lo, r1 AS hi, 'rows' AS side FROM blk WHERE level = {k}
 UNION ALL SELECT block_id, round, r0, c1, 4, 'all', c0, c1, 'columns' FROM blk WHERE level = {k}
 UNION ALL SELECT block_id, round, r0, c1, 2, 'LL+LU', s0, e0, 'columns' FROM blk JOIN ends ON l = level + 1 AND i = b WHERE level < {k}
 UNION ALL SELECT block_id, round, r0, c1, 3, 'LL+RL', s1, e1, 'rows' FROM blk JOIN ends ON l = level + 1 AND i = a WHERE level < {k}
 UNION ALL SELECT block_id, round, r0, c1, 4, 'RL+RU', s1, e1, 'columns' FROM blk JOIN ends ON l = level + 1 AND i = b WHERE level < {k}
 UNION ALL SELECT block_id, round, r0, c1, 5, 'LU+RU', s0, e0, 'rows' FROM blk JOIN ends ON l = level + 1 AND i = a WHERE level < {k}),
sent AS (SELECT pair.block_id, pair.step, pair.parts, o.owner AS dst_owner FROM pair JOIN blk x ON x.round > pair.round
  AND CASE WHEN side = 'rows' THEN x.r0 <= hi AND lo <= x.r1 AND x.c0 > pair.c1 ELSE x.c0 <= hi AND lo <= x.c1 AND x.r1 < pair.r0 END
 JOIN own o ON o.block_id = x.block_id JOIN own me ON me.block_id = pair.block_id WHERE o.owner <> me.owner)
{select}"""
