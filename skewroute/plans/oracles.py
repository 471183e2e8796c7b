"""DuckDB SQL that states what routing must give: streams, hashes, and sequential schemes as recursive queries.

Written from the definitions, not from the Python kernel: a message's candidates are a list, the load list is carried row
by row for each source, and the first least loaded candidate takes the message.
"""

from __future__ import annotations

EVENT_TYPES = "SELECT event_id AS seq, event_type AS key FROM events"
TOKENS = "SELECT doc_id, unnest(string_split(text, ' ')) AS key FROM documents"


def choice(i: int | str, n: int, key: str = "key") -> str:
    return f"(('0x' || substr(md5({i} || ':' || {key}), 1, 8))::BIGINT % {n})::INTEGER"


def zipf(keys: int, z: int, seed: int = 7) -> str:
    """``(seq, ts, key)`` of events drawn from integer Zipf cuts; z a whole number."""
    return f"""
  SELECT e.event_id AS seq, e.ts, k::VARCHAR AS key
  FROM (SELECT event_id, ts, ((('0x' || substr(md5('{seed}:' || event_id), 1, 8))::BIGINT * (SELECT sum(w) FROM zw)::BIGINT) >> 32) AS u FROM events) e
  JOIN zc ON e.u >= zc.lo AND e.u < zc.hi"""


def zipf_tables(keys: int, z: int) -> str:
    power = " * ".join(["k"] * z) if z else "1"
    return f"""zw AS (SELECT k, 100000000 // ({power}) AS w FROM range(1, {keys + 1}) t(k)),
zc AS (SELECT k, sum(w) OVER (ORDER BY k) - w AS lo, sum(w) OVER (ORDER BY k) AS hi FROM zw)"""


def sequential(messages: str, n: int, sources: int, before: str = "", columns: str = "seq, key, source_id, worker, is_head, n_choices") -> str:
    """Rows routed by carrying loads. ``messages`` gives ``seq`` (dense), ``key``, ``cs`` (candidates), ``turn`` (take
    the cursor instead), ``is_head`` and ``n_choices``."""
    return f"""
WITH RECURSIVE {before + ',' if before else ''}
m AS MATERIALIZED (SELECT seq, key, (seq % {sources})::INTEGER AS source_id, seq // {sources} AS i, cs, turn, is_head, n_choices FROM ({messages})),
r AS (
  SELECT source_id, -1::BIGINT AS i, -1::BIGINT AS seq, -1 AS worker, list_transform(range({n}), lambda x: 0::BIGINT) AS load, 0 AS cursor
  FROM (SELECT DISTINCT source_id FROM m)
  UNION ALL
  SELECT source_id, i, seq, w, list_transform(load, lambda x, k: x + CASE WHEN k = w + 1 THEN 1 ELSE 0 END), cursor + CASE WHEN turn THEN 1 ELSE 0 END
  FROM (
    SELECT m.source_id, m.i, m.seq, m.turn, r.load, r.cursor,
      (CASE WHEN m.turn THEN r.cursor % {n} ELSE m.cs[list_position(list_transform(m.cs, lambda c: r.load[c + 1]), list_min(list_transform(m.cs, lambda c: r.load[c + 1])))] END)::INTEGER AS w
    FROM r JOIN m ON m.source_id = r.source_id AND m.i = r.i + 1)),
routed AS (SELECT m.seq, m.key, m.source_id, r.worker, m.is_head, m.n_choices::INTEGER AS n_choices FROM r JOIN m USING (seq, source_id))
SELECT {columns} FROM routed"""


def two(n: int) -> str:
    return f"[{choice(1, n)}, {choice(2, n)}]"


def two_choice(stream: str, n: int, sources: int, before: str = "", **options) -> str:
    return sequential(f"SELECT seq, key, {two(n)} AS cs, FALSE AS turn, FALSE AS is_head, 2 AS n_choices FROM ({stream})", n, sources, before, **options)


def uniform(stream: str, n: int, d: int, sources: int, **options) -> str:
    cs = "[" + ", ".join(choice(i, n) for i in range(1, d + 1)) + "]"
    return sequential(f"SELECT seq, key, {cs} AS cs, FALSE AS turn, FALSE AS is_head, {d} AS n_choices FROM ({stream})", n, sources, **options)


def head(stream: str, n: int) -> str:
    """Keys with at least a fifth of a worker's share: ``(key, f, m, rank)``."""
    return f"""
f AS MATERIALIZED (SELECT key, count(*) AS f FROM ({stream}) GROUP BY key),
h AS MATERIALIZED (SELECT key, f, m, row_number() OVER (ORDER BY f DESC, key) AS rank FROM f, (SELECT sum(f) AS m FROM f) WHERE f * 5 * {n} >= m)"""


def constraints(n: int, eps: float = 1e-4) -> str:
    """Prefix conditions of the head table ``h``: ``(d, rank, lhs, rhs)``."""
    return f"""
u AS (SELECT rank, f / m AS p, sum(f / m) OVER (ORDER BY rank) AS upto, sum(f / m) OVER () AS whole, max(f / m) OVER () AS p1 FROM h),
b AS (SELECT d, u.*, {n} - {n} * pow({n - 1} / {n}, rank * d) AS b FROM u, range(2, {max(3, n)}) t(d) WHERE d >= greatest(2, ceil(p1 * {n}))),
c AS (SELECT d, rank, upto + pow(b / {n}, d) * (whole - upto) + pow(b / {n}, 2) * (1 - whole) AS lhs, b * (1.0 / {n} + {eps}) AS rhs FROM b),
dd AS (SELECT coalesce(min(d), {n})::INTEGER AS d FROM (SELECT d FROM c GROUP BY d HAVING bool_and(lhs <= rhs)))"""


def known_head(stream: str, n: int, sources: int, kind: str, d: int | None = None, before: str = "", **options) -> str:
    """Schemes whose head is the exact one."""
    tables = ", ".join(x for x in (before, head(stream, n), constraints(n) if kind == "tuned" else "") if x)
    everywhere = f"range({n})"
    if kind == "tuned":
        many = "(SELECT d FROM dd)"
        cs = f"CASE WHEN {many} >= {n} THEN {everywhere} ELSE list_transform(range(1, {many} + 1), lambda i: {choice('i', n, 's.key')}) END"
    elif kind == "fixed_head":
        many, cs = str(d), "[" + ", ".join(choice(i, n, "s.key") for i in range(1, d + 1)) + "]"
    else:
        many, cs = str(n), everywhere
    rows = f"""SELECT seq, s.key, CASE WHEN h.key IS NULL THEN {two(n).replace('key', 's.key')} ELSE {cs} END AS cs,
  h.key IS NOT NULL AND {str(kind == 'head_round_robin').upper()} AS turn, h.key IS NOT NULL AS is_head, CASE WHEN h.key IS NULL THEN 2 ELSE {many} END AS n_choices
FROM ({stream}) s LEFT JOIN h ON s.key = h.key"""
    return sequential(rows, n, sources, tables, **options)


def online_head(stream: str, n: int, sources: int, kind: str, before: str = "", **options) -> str:
    """Schemes that learn the head as they go, where the sketch holds all keys: a running count a source and key."""
    rows = f"""SELECT seq, key, CASE WHEN hot THEN range({n}) ELSE {two(n)} END AS cs, hot AND {str(kind == 'head_round_robin').upper()} AS turn, hot AS is_head, CASE WHEN hot THEN {n} ELSE 2 END AS n_choices
FROM (SELECT seq, key, count(*) OVER (PARTITION BY seq % {sources}, key ORDER BY seq) * 5 * {n} >= seq // {sources} + 1 AS hot FROM ({stream}))"""
    return sequential(rows, n, sources, before, **options)


def online_tuned(stream: str, keys: list[str], n: int, sources: int, eps: float = 1e-4) -> str:
    """The tuned scheme with d computed on every head row, where the sketch holds all of a few known keys.

    Each row knows its source's running counts of all keys; its head's shares give the least feasible d.
    """
    counts = ", ".join(f"count(*) FILTER (key = '{k}') OVER w" for k in keys)
    union = f"({n} - {n} * pow({n - 1} / {n}, h * d))"
    fits = f"list_sum(ps[1:h]) + pow({union} / {n}, d) * list_sum(ps[h + 1:]) + pow({union} / {n}, 2) * (1 - list_sum(ps)) <= {union} * (1.0 / {n} + {eps})"
    fits = fits.replace("list_sum(ps[h + 1:])", "coalesce(list_sum(ps[h + 1:]), 0)")
    rows = f"""SELECT seq, key, CASE WHEN NOT hot THEN {two(n)} WHEN d >= {n} THEN range({n}) ELSE list_transform(range(1, d + 1), lambda i: {choice('i', n)}) END AS cs,
  FALSE AS turn, hot AS is_head, CASE WHEN hot THEN d ELSE 2 END AS n_choices
FROM (
  SELECT seq, key, hot, coalesce(list_filter(range(greatest(2, ceil(ps[1] * {n}))::BIGINT, {n}), lambda d: len(list_filter(range(1, len(ps) + 1), lambda h: NOT ({fits}))) = 0)[1], {n})::INTEGER AS d
  FROM (
    SELECT seq, key, own * 5 * {n} >= m AS hot, list_transform(list_reverse_sort(list_filter(cs, lambda c: c * 5 * {n} >= m)), lambda c: c / m) AS ps
    FROM (SELECT seq, key, seq // {sources} + 1 AS m, count(*) OVER (PARTITION BY seq % {sources}, key ORDER BY seq) AS own, [{counts}] AS cs FROM ({stream}) WINDOW w AS (PARTITION BY seq % {sources} ORDER BY seq))))"""
    return sequential(rows, n, sources)


def zipf_choices(workers: list[int], z_grid: list[float], keys: int, eps: float = 1e-4) -> str:
    """Head size, start and computed d of exact Zipf shares."""
    grid = ", ".join(f"({n}, {z}::DOUBLE)" for n in workers for z in z_grid)
    return f"""
WITH g AS (SELECT * FROM (VALUES {grid}) v(n, z)),
w AS (SELECT z, k, pow(k, -z) AS w FROM (SELECT DISTINCT z FROM g), range(1, {keys + 1}) t(k)),
p AS (SELECT z, k, w / sum(w) OVER (PARTITION BY z) AS p FROM w),
h AS (SELECT n, z, k, p, sum(p) OVER (PARTITION BY n, z ORDER BY k) AS upto, sum(p) OVER (PARTITION BY n, z) AS whole, count(*) OVER (PARTITION BY n, z) AS size, max(p) OVER (PARTITION BY n, z) AS p1 FROM g JOIN p USING (z) WHERE p >= 1.0::DOUBLE / (5 * n)),
b AS (SELECT h.*, d, n - n * pow((n - 1) / n, k * d) AS b FROM h, range(2, {max(workers)}) t(d) WHERE d < n AND d >= greatest(2, ceil(p1 * n))),
ok AS (SELECT n, z, d FROM b GROUP BY n, z, d HAVING bool_and(upto + pow(b / n, d) * (whole - upto) + pow(b / n, 2) * (1 - whole) <= b * (1.0 / n + {eps}))),
top AS (SELECT g.n, g.z, p AS p1 FROM g JOIN p ON p.z = g.z AND k = 1)
SELECT top.n::INTEGER AS workers, top.z, coalesce(size, 0)::INTEGER AS head_size, greatest(2, ceil(top.p1 * top.n))::INTEGER AS start,
  CASE WHEN size IS NULL THEN 2 ELSE coalesce(d, top.n) END::INTEGER AS d, round(CASE WHEN size IS NULL THEN 2 ELSE coalesce(d, top.n) END / top.n, 9) AS fraction
FROM top LEFT JOIN (SELECT DISTINCT n, z, size FROM h) s ON s.n = top.n AND s.z = top.z LEFT JOIN (SELECT n, z, min(d) AS d FROM ok GROUP BY n, z) o ON o.n = top.n AND o.z = top.z"""


def load(routed: str, n: int) -> str:
    return f"""SELECT w.worker::INTEGER AS worker, coalesce(c, 0)::BIGINT AS messages, round(coalesce(c, 0) / m, 9) AS load
FROM range({n}) w(worker) LEFT JOIN (SELECT worker, count(*) AS c FROM ({routed}) GROUP BY worker) x ON x.worker = w.worker, (SELECT count(*) AS m FROM ({routed}))"""


def imbalance(routed: str, n: int) -> str:
    return f"SELECT round(max(c) / sum(c) - 1.0::DOUBLE / {n}, 9) AS imbalance FROM (SELECT count(*) AS c FROM ({routed}) GROUP BY worker)"


def shuffle(stream: str, n: int, sources: int) -> str:
    return f"SELECT seq, key, (seq % {sources})::INTEGER AS source_id, ((row_number() OVER (PARTITION BY seq % {sources} ORDER BY seq) - 1) % {n})::INTEGER AS worker FROM ({stream})"


def grouping(stream: str, n: int) -> str:
    return f"SELECT *, {choice(1, n)} AS worker FROM ({stream})"


def online_tuned_refresh(stream: str, keys: int, n: int, sources: int, refresh: int = 1000, before: str = "", eps: float = 1e-4, columns: str = "seq, key, source_id, worker, is_head, n_choices") -> str:
    """The tuned scheme as it learns, with d computed when a key enters the head and at the latest after ``refresh`` head rows.

    Keys are the numbers 1 to ``keys`` as text, all of which the sketch holds. Each row knows its source's running counts of all keys; the loads, d, its age and the
    hot keys are carried from row to row.
    """
    counts = ", ".join(f"count(*) FILTER (key = '{k}') OVER w" for k in range(1, keys + 1))
    union = f"({n} - {n} * pow({n - 1} / {n}, h * d))"
    fits = f"list_sum(ps[1:h]) + pow({union} / {n}, d) * coalesce(list_sum(ps[h + 1:]), 0) + pow({union} / {n}, 2) * (1 - list_sum(ps)) <= {union} * (1.0 / {n} + {eps})"
    return f"""
WITH RECURSIVE {before + ',' if before else ''}
m AS MATERIALIZED (
  SELECT seq, key, key::INTEGER AS k, (seq % {sources})::INTEGER AS source_id, seq // {sources} AS i, seq // {sources} + 1 AS m, cs, cs[key::INTEGER] * 5 * {n} >= seq // {sources} + 1 AS is_head, {two(n)} AS pair
  FROM (SELECT seq, key, [{counts}] AS cs FROM ({stream}) WINDOW w AS (PARTITION BY seq % {sources} ORDER BY seq))),
r AS (
  SELECT source_id, -1::BIGINT AS i, -1::BIGINT AS seq, -1 AS worker, 2 AS used, list_transform(range({n}), lambda x: 0::BIGINT) AS load, 2 AS d, 0 AS age, []::INTEGER[] AS hot FROM (SELECT DISTINCT source_id FROM m)
  UNION ALL
  SELECT source_id, i, seq, w, CASE WHEN is_head THEN d ELSE 2 END, list_transform(load, lambda x, j: x + CASE WHEN j = w + 1 THEN 1 ELSE 0 END), d, age, hot
  FROM (
    SELECT *, (cand[list_position(list_transform(cand, lambda c: load[c + 1]), list_min(list_transform(cand, lambda c: load[c + 1])))])::INTEGER AS w
    FROM (
      SELECT *, CASE WHEN NOT is_head THEN pair WHEN d >= {n} THEN range({n})::INTEGER[] ELSE list_transform(range(1, d + 1), lambda c: {choice('c', n)}) END AS cand
      FROM (
        SELECT source_id, i, seq, key, is_head, pair, load, hot, age,
          CASE WHEN anew THEN coalesce(list_filter(range(greatest(2, ceil(ps[1] * {n}))::BIGINT, {n}), lambda d: len(list_filter(range(1, len(ps) + 1), lambda h: NOT ({fits}))) = 0)[1], {n})::INTEGER ELSE old END AS d
        FROM (
          SELECT *, CASE WHEN anew THEN list_transform(list_reverse_sort(list_transform(hot, lambda x: cs[x])), lambda c: c / m) ELSE []::DOUBLE[] END AS ps
          FROM (
            SELECT m.source_id, m.i, m.seq, m.key, m.is_head, m.pair, m.cs, m.m, r.load, r.d AS old,
              m.is_head AND (NOT list_contains(r.hot, m.k) OR r.age + 1 >= {refresh}) AS anew,
              CASE WHEN NOT m.is_head THEN r.age WHEN NOT list_contains(r.hot, m.k) OR r.age + 1 >= {refresh} THEN 0 ELSE r.age + 1 END AS age,
              CASE WHEN m.is_head AND (NOT list_contains(r.hot, m.k) OR r.age + 1 >= {refresh}) THEN list_filter(list_distinct(list_append(r.hot, m.k)), lambda x: m.cs[x] * 5 * {n} >= m.m) ELSE r.hot END AS hot
            FROM r JOIN m ON m.source_id = r.source_id AND m.i = r.i + 1)))))),
routed AS (SELECT m.seq, m.key, m.source_id, r.worker, m.is_head, r.used::INTEGER AS n_choices FROM r JOIN m USING (seq, source_id))
SELECT {columns} FROM routed"""


def _zipf_points(workers: list[int], z_grid: list[float], keys: int) -> str:
    grid = ", ".join(f"({n}, {z}::DOUBLE)" for n in workers for z in z_grid)
    return f"""g AS (SELECT * FROM (VALUES {grid}) v(n, z)),
w AS (SELECT z, k, pow(k, -z) AS w FROM (SELECT DISTINCT z FROM g), range(1, {keys + 1}) t(k)),
p AS (SELECT z, k, w / sum(w) OVER (PARTITION BY z) AS p FROM w)"""


def zipf_heads(workers: list[int], z_grid: list[float], keys: int) -> str:
    """Head sizes of exact Zipf shares at both ends of the range of thresholds."""
    return f"WITH {_zipf_points(workers, z_grid, keys)} SELECT n::INTEGER AS workers, z, round(th, 4) AS theta_n, count(*) FILTER (p >= th / n)::INTEGER AS head_size FROM g JOIN p USING (z), (VALUES (2.0::DOUBLE), (0.2)) b(th) GROUP BY ALL"


def zipf_memory(workers: list[int], z_grid: list[float], keys: int, messages: int) -> str:
    """Estimated state of exact Zipf shares, in percent more than two choices and shuffling."""
    return f"""
WITH {_zipf_points(workers, z_grid, keys)},
c AS (SELECT workers AS n, z, d FROM ({zipf_choices(workers, z_grid, keys)})),
f AS (SELECT g.n, g.z, d, round_even(p * {messages}, 0) AS f, p >= 1.0::DOUBLE / (5 * g.n) AS hot FROM g JOIN p USING (z) JOIN c ON c.n = g.n AND c.z = g.z),
e AS (SELECT n, z, sum(least(f, 2)) AS two, sum(least(f, n)) AS every, sum(least(f, CASE WHEN hot THEN d ELSE 2 END)) AS tuned, sum(least(f, CASE WHEN hot THEN n ELSE 2 END)) AS anyw FROM f GROUP BY n, z)
SELECT n::INTEGER AS workers, z, scheme, round(100 * (own / two - 1), 6) AS vs_two_choice, round(100 * (own / every - 1), 6) AS vs_shuffle
FROM e, LATERAL (VALUES ('tuned', tuned), ('any_worker', anyw), ('head_round_robin', anyw)) v(scheme, own)"""


def drawn_counts(keys: int, scales: dict[float, int], seed: int = 7) -> str:
    """How often the rows of events draw each key at each skew, by integer cuts: tables ``c(z, key, f)`` and ``mm(z, m, p1)``. ``scales``: of the weights, by skew."""
    weights = " UNION ALL ".join(f"SELECT {z}::DOUBLE AS z, k, ({f'{scale} // (' + ' * '.join(['k'] * int(z)) + ')' if float(z).is_integer() else f'round_even({scale}::DOUBLE * pow(k, -{z}::DOUBLE), 0)'})::BIGINT AS w FROM range(1, {keys + 1}) t(k)" for z, scale in scales.items())
    return f"""dw AS MATERIALIZED ({weights}),
dc AS MATERIALIZED (SELECT z, k, sum(w) OVER (PARTITION BY z ORDER BY k) - w AS lo FROM dw WHERE w > 0),
dt AS MATERIALIZED (SELECT z, sum(w)::BIGINT AS total FROM dw GROUP BY z),
du AS (SELECT z, ((('0x' || substr(md5('{seed}:' || event_id), 1, 8))::BIGINT * total) >> 32)::HUGEINT AS u FROM events, dt),
c AS MATERIALIZED (SELECT du.z, dc.k AS key, count(*) AS f FROM du ASOF JOIN dc ON du.z = dc.z AND du.u >= dc.lo GROUP BY du.z, dc.k),
mm AS MATERIALIZED (SELECT z, sum(f) AS m, max(f) / sum(f) AS p1 FROM c GROUP BY z)"""


def _drawn_choices(workers: list[int], eps: float = 1e-4) -> str:
    """Heads and computed d of drawn counts: tables ``g(n, z, m, p1)`` and ``dd(n, z, head_size, d)``."""
    return f"""g AS MATERIALIZED (SELECT n, z, m, p1 FROM mm, (VALUES {', '.join(f'({n})' for n in workers)}) v(n)),
h AS MATERIALIZED (SELECT n, z, f / m AS p, p1, row_number() OVER (PARTITION BY n, z ORDER BY f DESC, key) AS rank FROM g JOIN c USING (z) WHERE f * 5 * n >= m),
hh AS MATERIALIZED (SELECT *, sum(p) OVER (PARTITION BY n, z ORDER BY rank) AS upto, sum(p) OVER (PARTITION BY n, z) AS whole FROM h),
b AS (SELECT hh.*, d, n - n * pow((n - 1) / n, rank * d) AS b FROM hh, range(2, {max(workers)}) t(d) WHERE d < n AND d >= greatest(2, ceil(p1 * n))),
ok AS MATERIALIZED (SELECT n, z, d FROM b GROUP BY n, z, d HAVING bool_and(upto + pow(b / n, d) * (whole - upto) + pow(b / n, 2) * (1 - whole) <= b * (1.0 / n + {eps}))),
dd AS MATERIALIZED (SELECT g.n, g.z, any_value(p1) AS p1, any_value(coalesce(size, 0)) AS head_size, CASE WHEN any_value(size) IS NULL THEN 2 ELSE coalesce(min(d), g.n) END AS d
  FROM g LEFT JOIN (SELECT n, z, count(*) AS size FROM h GROUP BY n, z) s ON s.n = g.n AND s.z = g.z LEFT JOIN ok ON ok.n = g.n AND ok.z = g.z GROUP BY g.n, g.z)"""


def drawn_choices(workers: list[int], scales: dict[float, int], keys: int) -> str:
    """Head size, start and computed d of keys that the rows of events draw."""
    return f"""WITH {drawn_counts(keys, scales)}, {_drawn_choices(workers)}
SELECT n::INTEGER AS workers, z, head_size::INTEGER AS head_size, greatest(2, ceil(p1 * n))::INTEGER AS start, d::INTEGER AS d, round(d / n, 9) AS fraction FROM dd"""


def drawn_heads(workers: list[int], scales: dict[float, int], keys: int) -> str:
    """Head sizes of the same at both ends of the range of thresholds."""
    return f"WITH {drawn_counts(keys, scales)} SELECT n::INTEGER AS workers, z, th::DOUBLE / 10 AS theta_n, count(*) FILTER (f * n * 10 >= th * m)::INTEGER AS head_size FROM c JOIN mm USING (z), (VALUES {', '.join(f'({n})' for n in workers)}) v(n), (VALUES (20), (2)) b(th) GROUP BY n, z, th"


def drawn_memory(workers: list[int], scales: dict[float, int], keys: int) -> str:
    """Estimated state of the same, in percent more than two choices and shuffling."""
    return f"""
WITH {drawn_counts(keys, scales)}, {_drawn_choices(workers)},
e AS (SELECT n, z, sum(least(f, 2)) AS two, sum(least(f, n)) AS every, sum(least(f, CASE WHEN f * 5 * n >= m THEN d ELSE 2 END)) AS tuned, sum(least(f, CASE WHEN f * 5 * n >= m THEN n ELSE 2 END)) AS anyw
  FROM g JOIN c USING (z) JOIN (SELECT n, z, d FROM dd) x USING (n, z) GROUP BY n, z)
SELECT n::INTEGER AS workers, z, scheme, round(100 * (own / two - 1), 6) AS vs_two_choice, round(100 * (own / every - 1), 6) AS vs_shuffle
FROM e, LATERAL (VALUES ('tuned', tuned), ('any_worker', anyw), ('head_round_robin', anyw)) v(scheme, own)"""
