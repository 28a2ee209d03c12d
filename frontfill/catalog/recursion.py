"""DuckDB recursions that recompute fills and thinnings from their definitions, one test at a time."""

from __future__ import annotations

from frontfill.functions.directions import directions

H2 = "CAST(FLOOR(6000000.0 * SQRT(2.8::DOUBLE / {n})) AS BIGINT)"
H3 = "CAST(FLOOR(6000000.0 * POW(3.4::DOUBLE / {n}, 1.0::DOUBLE / 3)) AS BIGINT)"


def mix(e: str) -> str:
    return f"((({e}) * 48271 + 11) % 2147483647)"


def turn(d: int, name: str) -> str:
    e = mix(f"{name}0")
    for a in range(1, d):
        e = mix(f"{e} + {name}{a}")
    return f"({e} % 5)"


def direction_lists(d: int, k: int | None = None) -> list[str]:
    t = directions(d, k)
    return ["[" + ", ".join(str(int(v)) for v in t[:, :, a].ravel()) + "]::BIGINT[]" for a in range(d)]


def _far(d: int, points: str = "p", at: str = "n") -> str:
    """Squared distance of list element i to the candidate."""
    return " + ".join(f"({points}{a}[i] - {at}{a}) * ({points}{a}[i] - {at}{a})" for a in range(d))


def sequential(params: str, seeds: list[str], inside: str, h_at: str, d: int, k: int | None = None, annulus: bool = False, select: str | None = None) -> str:
    """First-in-first-out fill.

    ``params``: SELECT of one row of parameters; ``seeds``: a list expression an axis, already thinned;
    ``inside``/``h_at``: expressions over ``{x}0..`` with ``{x}`` the coordinate name, and parameters.
    """
    kk = directions(d, k).shape[1]
    dirs = direction_lists(d, k)
    reach = "(ph + 3)"
    if annulus:
        inner = mix("rot_raw + k")
        reach = f"(ph + 3 + ph * ({mix(inner + ' + k')} % 1024) // 1024)"
    raw = mix("px0")
    for a in range(1, d):
        raw = mix(f"{raw} + px{a}")
    cand = ", ".join(f"((px{a} << 20) + {reach} * d{a}[(rot_raw % 5) * {kk} + k + 1] + 524288) >> 20 AS n{a}" for a in range(d))
    cols = ", ".join(f"p{a}" for a in range(d))
    return f"""
WITH RECURSIVE prm AS ({params}),
tab AS (SELECT {', '.join(f'{x} AS d{a}' for a, x in enumerate(dirs))}),
s AS (
  SELECT 0 AS step, 1 AS head, 0 AS k, {', '.join(f'{x} AS p{a}' for a, x in enumerate(seeds))},
         list_transform(range(1, len({seeds[0]}) + 1), lambda i: 0::BIGINT) AS hp, list_transform(range(1, len({seeds[0]}) + 1), lambda i: 0) AS par FROM prm
  UNION ALL
  SELECT step + 1, CASE WHEN k = {kk - 1} THEN head + 1 ELSE head END, CASE WHEN k = {kk - 1} THEN 0 ELSE k + 1 END,
         {', '.join(f'CASE WHEN ok THEN list_append(p{a}, n{a}) ELSE p{a} END' for a in range(d))},
         CASE WHEN ok THEN list_append(hp, ph) ELSE hp END, CASE WHEN ok THEN list_append(par, head) ELSE par END
  FROM (
    SELECT *, ({inside.format(x='n')}) AND len(list_filter(range(1, len(p0) + 1), lambda i: {_far(d)} < ph * ph)) = 0 AS ok
    FROM (SELECT *, {cand}
          FROM (SELECT *, {raw} AS rot_raw
                FROM (SELECT *, {h_at.format(x='px')} AS ph
                      FROM (SELECT s.*, prm.*, tab.*, {', '.join(f'p{a}[head] AS px{a}' for a in range(d))} FROM s, prm, tab WHERE head <= len(p0)))))
  )
),
z AS (SELECT * FROM s ORDER BY step DESC LIMIT 1),
u AS (SELECT unnest(range(1, len(p0) + 1)) AS i, {cols}, hp, par FROM z)
SELECT {select or 'i - 1 AS seq'}, {', '.join(f'p{a}[i] AS x{a}' for a in range(d))},
       CASE WHEN par[i] = 0 THEN {h_at.format(x='q')} ELSE hp[i] END AS h_parent, (par[i] - 1)::BIGINT AS parent
FROM (SELECT *, {', '.join(f'p{a}[i] AS q{a}' for a in range(d))} FROM u), prm
"""


def phased(params: str, level: int, inside: str, select_level: int) -> str:
    """Phase-coloured fill in the plane on a full tree of one level, constant spacing ``h``, a seed a cell, cell after cell."""
    n = 1 << level
    half = n // 2
    shift = 24 - level
    dx, dy = direction_lists(2)
    mor = " + ".join(f"(((({{x}} >> {b}) & 1) << {2 * b + 1}) | ((({{y}} >> {b}) & 1) << {2 * b}))" for b in range(level)) or "0"
    rank = f"((2 * (({{x}}) & 1) + (({{y}}) & 1)) * {half * half} + (({{x}}) >> 1) * {half} + (({{y}}) >> 1))"
    # cell coordinates of a rank
    cx = f"(2 * ((rank % {half * half}) // {half}) + ((rank // {half * half}) >> 1))"
    cy = f"(2 * (rank % {half}) + ((rank // {half * half}) & 1))"
    key = lambda x, y: f"({1 << (2 * level)} + {mor.format(x=x, y=y)})"
    return f"""
WITH RECURSIVE prm AS ({params}),
tab AS (SELECT {dx} AS d0, {dy} AS d1),
s AS (
  SELECT 0 AS step, 1 AS stage, 0::BIGINT AS rank, 0 AS k, []::BIGINT[] AS p0, []::BIGINT[] AS p1, []::BIGINT[] AS cs, []::BOOLEAN[] AS es, []::BIGINT[] AS bys, []::BIGINT[] AS st, false AS stop
  UNION ALL
  SELECT step + 1,
    CASE WHEN cur IS NULL AND NOT seed AND rank = {n * n - 1} THEN stage + 1 ELSE stage END,
    CASE WHEN cur IS NULL AND NOT seed THEN CASE WHEN rank = {n * n - 1} THEN 0 ELSE rank + 1 END ELSE rank END,
    CASE WHEN cur IS NULL OR k = 11 THEN 0 ELSE k + 1 END,
    CASE WHEN ok THEN list_append(p0, n0) ELSE p0 END, CASE WHEN ok THEN list_append(p1, n1) ELSE p1 END,
    CASE WHEN ok THEN list_append(cs, {rank.format(x=f'(n0 >> {shift})', y=f'(n1 >> {shift})')}) ELSE cs END,
    list_concat(CASE WHEN cur IS NOT NULL AND k = 11 THEN list_concat(list_append(es[1:cur-1], true), es[cur+1:]) ELSE es END, CASE WHEN ok THEN [false] ELSE []::BOOLEAN[] END),
    CASE WHEN ok THEN list_append(bys, rank) ELSE bys END, CASE WHEN ok THEN list_append(st, stage) ELSE st END,
    cur IS NULL AND NOT seed AND rank = {n * n - 1} AND NOT list_contains(es, false)
  FROM (
    SELECT *, seed0 AND ok AS seed FROM (
    SELECT *, (cur IS NOT NULL OR seed0) AND ({inside.format(x='n')}) AND len(list_filter(range(1, len(p0) + 1), lambda i: {_far(2)} < h * h)) = 0 AS ok
    FROM (
      SELECT *, cur IS NULL AND stage = 1 AND NOT list_contains(cs, rank) AS seed0,
        CASE WHEN cur IS NULL THEN ({cx} << {shift}) + {1 << (shift - 1)} ELSE ((p0[cur] << 20) + (h + 3) * d0[{turn(2, 'px')} * 12 + k + 1] + 524288) >> 20 END AS n0,
        CASE WHEN cur IS NULL THEN ({cy} << {shift}) + {1 << (shift - 1)} ELSE ((p1[cur] << 20) + (h + 3) * d1[{turn(2, 'px')} * 12 + k + 1] + 524288) >> 20 END AS n1
      FROM (SELECT *, p0[cur] AS px0, p1[cur] AS px1 FROM (
        SELECT s.*, prm.*, tab.*, list_filter(range(1, len(p0) + 1), lambda i: cs[i] = rank AND NOT es[i])[1] AS cur FROM s, prm, tab WHERE NOT stop))))
  )
),
z AS (SELECT * FROM s ORDER BY step DESC LIMIT 1),
u AS (SELECT unnest(range(1, len(p0) + 1)) AS i, p0, p1, bys, st, prm.h FROM z, prm),
v AS (SELECT i, p0[i] AS x0, p1[i] AS x1, bys[i] AS rank, st[i] AS stage, h FROM u)
SELECT x0, x1, h, h AS h_parent, {key(f'(x0 >> {shift})', f'(x1 >> {shift})')} AS cell, {key(cx, cy)} AS by_cell,
       stage::BIGINT AS stage, (rank // {half * half})::BIGINT AS phase,
       row_number() OVER (PARTITION BY stage, rank ORDER BY i) - 1 AS seq
FROM v
"""


def thinned(rows: str, d: int, extra: str = "", group: str | None = None) -> str:
    """Greedy thinning of ``rows`` (``id, h, x0..`` and a group) by hashed priority, one row at a time."""
    grp = group or "0"
    xs = ", ".join(f"x{a}" for a in range(d))
    return f"""
WITH RECURSIVE src AS ({rows}),
o AS (SELECT *, row_number() OVER (PARTITION BY g ORDER BY {mix(mix('id'))}, id) AS r, count(*) OVER (PARTITION BY g) AS m
      FROM (SELECT *, {grp} AS g FROM src)),
s AS (
  SELECT g, 0::BIGINT AS r, m, []::BIGINT[] AS ids, {', '.join(f'[]::BIGINT[] AS p{a}' for a in range(d))} FROM o WHERE r = 1
  UNION ALL
  SELECT g, nr, m, CASE WHEN ok THEN list_append(ids, id) ELSE ids END,
         {', '.join(f'CASE WHEN ok THEN list_append(p{a}, n{a}) ELSE p{a} END' for a in range(d))}
  FROM (SELECT *, len(list_filter(range(1, len(ids) + 1), lambda i: {_far(d)} < h * h)) = 0 AS ok
        FROM (SELECT s.g, s.m, s.ids, {', '.join(f's.p{a}' for a in range(d))}, o.r AS nr, o.id, o.h, {', '.join(f'o.x{a} AS n{a}' for a in range(d))}
              FROM s JOIN o ON o.g = s.g AND o.r = s.r + 1))
)
SELECT {extra}{xs_id(d)} FROM (SELECT g, unnest(ids) AS id FROM s WHERE r = m) k JOIN o USING (g, id)
"""


def xs_id(d: int) -> str:
    return "id, " + ", ".join(f"x{a}" for a in range(d))
