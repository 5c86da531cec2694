"""The iterative methods replayed in DuckDB SQL, step by step, as oracles of whole runs.

Each builder gives common table expressions over ``b`` (src, dst, w, pw: both directions of every edge) for a query that
begins with ``WITH RECURSIVE``. A recursion's row is a node's state in one step together with the figures of the run."""

from __future__ import annotations

from spanweave.functions.hashing import SCALE, h32_sql
from spanweave.operators.decompose import GAMMA

EDGES = "b AS (SELECT src, dst, {grow} AS w, w AS pw FROM e UNION ALL SELECT dst, src, {grow}, w FROM e)"


def both(edges: str, hops: bool = False) -> str:
    """e and b of an edge query."""
    return f"e AS ({edges}), {EDGES.format(grow='1::BIGINT' if hops else 'w')}"


MEAN = "(SELECT ((sum(w) + count(*) - 1) // count(*))::BIGINT FROM b)"
LEAST = "(SELECT min(w) FROM b)"


def staged(
    tau: int | str = 1, *, seed: int = 7, delta0: str = MEAN, count: str = "uncovered", cap: str | None = None, name: str = "st"
) -> str:
    """``{name}``: node, center, path_weight, stage of the staged decomposition; ``{name}_steps``: a row per growing step;
    ``{name}_run``: delta_end, stages, guesses, radius, clusters, growing_steps, work."""
    base = "CASE WHEN settled IS NULL THEN d ELSE 0 END"
    whole = "2 * (clusters + covered) >= clusters + still" if count == "all_nodes" else "false"
    capped = f"taken >= {cap}" if cap else "false"
    gamma = f"{GAMMA!r}::DOUBLE * ({tau})"
    return f"""
{name}_v AS MATERIALIZED (SELECT DISTINCT src AS node FROM b), {name}_n AS MATERIALIZED (SELECT count(*) AS n, log2(count(*)) AS log_n FROM {name}_v),
{name}_r AS (
  SELECT 0 AS it, node, NULL::BIGINT AS center, NULL::BIGINT AS d, NULL::BIGINT AS path, NULL::INT AS settled, false AS active, 0 AS stage, 0 AS guess, 0 AS taken,
    {delta0} AS delta, n AS still, 0::BIGINT AS clusters, true AS fresh, n < 8 * ({tau}) * log_n AS done, 0 AS at_stage, 0 AS at_guess, 0::BIGINT AS at_delta,
    0::BIGINT AS messages, 0::BIGINT AS combined, 0::BIGINT AS updates, 0::BIGINT AS covered, n AS uncovered
  FROM {name}_v, {name}_n
  UNION ALL
  SELECT * FROM (
    WITH h AS (SELECT *, CASE WHEN fresh AND center IS NULL THEN {h32_sql(f"'{seed}:' || stage || ':' || node")} END AS draw FROM {name}_r WHERE NOT done),
    c AS (SELECT *, draw < least(1.0::DOUBLE, {gamma} * log_n / still) * {SCALE}::DOUBLE AS drawn FROM h, {name}_n),
    none AS (SELECT arg_min(node, {{'h': draw, 'v': node}}) AS one FROM c HAVING count(*) FILTER (drawn OR center IS NOT NULL) = 0),
    p AS (SELECT c.* EXCLUDE (center, d, path, active, n, log_n), coalesce(drawn, false) OR coalesce(node = one, false) AS new,
        CASE WHEN new THEN node ELSE center END AS center, CASE WHEN new THEN 0 ELSE d END AS d, CASE WHEN new THEN 0 ELSE path END AS path, active OR new AS active
      FROM c LEFT JOIN none ON true),
    o AS (SELECT b.dst, min({{'d': base + b.w, 'c': center, 'p': path + b.pw}}) AS o, count(*) AS n FROM (SELECT *, {base} AS base FROM p WHERE center IS NOT NULL AND active) p
      JOIN b ON b.src = p.node WHERE base < delta AND b.w <= delta AND base + b.w <= delta GROUP BY b.dst),
    g AS (SELECT p.*, o.n, o.o, settled IS NULL AND o.o IS NOT NULL AND (d IS NULL OR o.o.d < d) AS taking FROM p LEFT JOIN o ON o.dst = p.node),
    s AS (SELECT it + 1 AS it, node, CASE WHEN taking THEN o.c ELSE center END AS center, CASE WHEN taking THEN o.d ELSE d END AS d, CASE WHEN taking THEN o.p ELSE path END AS path,
        settled, taking AS active, stage, guess + fresh::INT AS guess, CASE WHEN fresh THEN 0 ELSE taken END + 1 AS taken, delta, still, clusters, n, taking FROM g),
    f AS (SELECT coalesce(sum(n), 0)::BIGINT AS messages, count(n) AS combined, count(*) FILTER (taking) AS updates, count(*) FILTER (center IS NOT NULL AND settled IS NULL) AS covered,
        count(*) FILTER (center IS NULL) AS uncovered, count(*) FILTER (center = node) AS centers FROM s),
    edge AS (SELECT count(*) > 0 AS boundary FROM b JOIN s x ON x.node = b.src JOIN s y ON y.node = b.dst WHERE x.center IS NOT NULL AND y.center IS NULL),
    z AS (SELECT s.* EXCLUDE (n, taking), f.*, 2 * covered >= still AS half, half OR (updates = 0 AND NOT boundary) AS settles, NOT settles AND (updates = 0 OR {whole} OR {capped}) AS doubles
      FROM s, f, edge)
    SELECT it, node, center, d, path, CASE WHEN settles AND settled IS NULL AND center IS NOT NULL THEN stage ELSE settled END AS settled,
      CASE WHEN settles OR doubles THEN center IS NOT NULL ELSE active END AS active, stage + settles::INT AS stage, guess + doubles::INT AS guess, CASE WHEN doubles THEN 0 ELSE taken END AS taken,
      CASE WHEN doubles THEN delta * 2 ELSE delta END AS delta, CASE WHEN settles THEN uncovered ELSE still END AS still, CASE WHEN settles THEN centers ELSE clusters END AS clusters,
      settles AS fresh, settles AND (uncovered = 0 OR uncovered < 8 * ({tau}) * log_n) AS done, stage AS at_stage, guess AS at_guess, delta AS at_delta, messages, combined, updates, covered, uncovered
    FROM z, {name}_n)),
{name}_last AS MATERIALIZED (SELECT * FROM {name}_r WHERE it = (SELECT max(it) FROM {name}_r)),
{name} AS MATERIALIZED (SELECT node, coalesce(center, node) AS center, coalesce(path, 0)::BIGINT AS path_weight, coalesce(settled, stage) AS stage FROM {name}_last),
{name}_steps AS MATERIALIZED (SELECT DISTINCT it, at_stage AS stage, at_guess AS guess, at_delta AS delta, messages, combined, updates, covered, uncovered FROM {name}_r WHERE it > 0),
{name}_run AS MATERIALIZED (SELECT (SELECT max(delta) FROM {name}_last) AS delta_end, (SELECT max(stage) FROM {name}_last)::BIGINT AS stages, (SELECT max(guess) FROM {name}_last)::BIGINT AS guesses,
  (SELECT max(path_weight) FROM {name}) AS radius, (SELECT count(*) FROM {name} WHERE node = center) AS clusters,
  (SELECT count(*) FROM {name}_steps) AS growing_steps, (SELECT coalesce(sum(messages + updates), 0)::BIGINT FROM {name}_steps) AS work)"""


def rescaled(tau: int = 1, *, seed: int = 7, delta0: str = MEAN) -> str:
    """``rs`` and ``rs_run`` of the rescaled decomposition, from twice the radius of the staged one (``st``)."""
    base = "CASE WHEN settled IS NULL THEN d ELSE shift END"
    return f"""{staged(tau, seed=seed, delta0=delta0)},
k AS MATERIALIZED (SELECT 2 * radius AS reach, greatest(1, ceil(log_n))::INT AS last FROM st_run, st_n),
rs_r AS (
  SELECT 0 AS it, node, NULL::BIGINT AS center, NULL::BIGINT AS d, NULL::BIGINT AS path, NULL::INT AS settled, NULL::BIGINT AS shift, false AS active,
    1 AS stage, true AS fresh, false AS done, 0::BIGINT AS messages, 0::BIGINT AS updates FROM st_v
  UNION ALL
  SELECT * FROM (
    WITH c AS (SELECT r.*, k.*, n, fresh AND center IS NULL AND (stage = last OR {h32_sql(f"'{seed + 1}:' || stage || ':' || node")} < least(1.0::DOUBLE, (1 << stage)::DOUBLE / n) * {SCALE}::DOUBLE) AS new
      FROM (SELECT * FROM rs_r WHERE NOT done) r, k, st_n),
    p AS (SELECT c.* EXCLUDE (center, d, path, active), CASE WHEN new THEN node ELSE center END AS center, CASE WHEN new THEN 0 ELSE d END AS d, CASE WHEN new THEN 0 ELSE path END AS path, active OR new AS active FROM c),
    o AS (SELECT b.dst, min({{'d': greatest(base + b.w, 0), 'c': center, 'p': path + b.pw}}) AS o, count(*) AS n FROM (SELECT *, {base} AS base FROM p WHERE center IS NOT NULL AND active) p
      JOIN b ON b.src = p.node WHERE base < reach AND b.w <= reach AND base + b.w <= reach GROUP BY b.dst),
    g AS (SELECT p.* EXCLUDE (n), o.n, o.o, settled IS NULL AND o.o IS NOT NULL AND (d IS NULL OR o.o.d < d) AS taking FROM p LEFT JOIN o ON o.dst = p.node),
    s AS (SELECT it + 1 AS it, node, CASE WHEN taking THEN o.c ELSE center END AS center, CASE WHEN taking THEN o.d ELSE d END AS d, CASE WHEN taking THEN o.p ELSE path END AS path,
        settled, shift, taking AS active, stage, n, taking, reach FROM g),
    f AS (SELECT coalesce(sum(n), 0)::BIGINT AS messages, count(*) FILTER (taking) AS updates, count(*) FILTER (center IS NULL) AS uncovered FROM s)
    SELECT it, node, center, d, path, CASE WHEN f.updates = 0 AND settled IS NULL AND center IS NOT NULL THEN stage ELSE settled END AS settled,
      CASE WHEN f.updates > 0 THEN shift WHEN settled IS NULL AND center IS NOT NULL THEN d - reach END AS shift,
      CASE WHEN f.updates > 0 THEN active ELSE settled IS NULL AND center IS NOT NULL END AS active, stage + (f.updates = 0)::INT AS stage, f.updates = 0 AS fresh,
      f.updates = 0 AND (f.uncovered = 0 OR stage = (SELECT last FROM k)) AS done, f.messages, f.updates
    FROM s, f)),
rs_last AS MATERIALIZED (SELECT * FROM rs_r WHERE it = (SELECT max(it) FROM rs_r)),
rs AS MATERIALIZED (SELECT node, center, path AS path_weight, settled AS stage FROM rs_last),
rs_steps AS MATERIALIZED (SELECT DISTINCT it, messages, updates FROM rs_r WHERE it > 0),
rs_run AS MATERIALIZED (SELECT (SELECT reach FROM k) AS delta_end, (SELECT max(stage) - 1 FROM rs_last)::BIGINT AS stages, (SELECT max(stage) - 1 FROM rs_last)::BIGINT AS guesses,
  (SELECT max(path_weight) FROM rs) AS radius, (SELECT count(*) FROM rs WHERE node = center) AS clusters,
  (SELECT growing_steps FROM st_run) + (SELECT count(*) FROM rs_steps) AS growing_steps, (SELECT work FROM st_run) + (SELECT sum(messages + updates)::BIGINT FROM rs_steps) AS work,
  (SELECT stages FROM st_run) + (SELECT max(stage) - 1 FROM rs_last) AS contractions)"""


def quotient(name: str = "st") -> str:
    """``q``: the quotient's edges; ``qd``: distances of all its pairs."""
    return f"""
q AS MATERIALIZED (SELECT least(x.center, y.center) AS src, greatest(x.center, y.center) AS dst, min(b.pw + x.path_weight + y.path_weight) AS w
  FROM b JOIN {name} x ON x.node = b.src JOIN {name} y ON y.node = b.dst WHERE b.src < b.dst AND x.center <> y.center GROUP BY ALL),
qb AS MATERIALIZED (SELECT src, dst, w FROM q UNION ALL SELECT dst, src, w FROM q),
qd(a, z, d) USING KEY (a, z) AS (SELECT DISTINCT src, src, 0::BIGINT FROM qb
  UNION SELECT x.a, x.z, x.d FROM (SELECT qd.a, qb.dst AS z, min(qd.d + qb.w) AS d FROM qd JOIN qb ON qb.src = qd.z GROUP BY ALL) x
    LEFT JOIN recurring.qd old ON old.a = x.a AND old.z = x.z WHERE old.a IS NULL OR x.d < old.d)"""


def figures(method: str, name: str = "st", contractions: str = "stages") -> str:
    """The row of an estimate over ``{name}_run``, ``q`` and ``qd``."""
    return f"""SELECT '{method}' AS method, phi + 2 * radius AS estimate, phi AS quotient_diameter, radius, clusters, (SELECT count(*) FROM q) AS quotient_edges, delta_end, stages, guesses,
  growing_steps, growing_steps + {contractions} + 2 AS rounds, work FROM {name}_run, (SELECT coalesce(max(d), 0)::BIGINT AS phi FROM qd)"""


def bucketed(source: str, width: str | None, name: str = "ss") -> str:
    """``{name}_run``: rounds, work and eccentricity of a search by buckets of ``width`` (null: one bucket)."""
    here = f"floor(dist / ({width})::DOUBLE)::BIGINT" if width else "0::BIGINT"
    light, heavy = (f"b.pw <= {width}", f"b.pw > {width}") if width else ("true", "false")
    two = "true" if width else "false"
    return f"""
{name}_r AS (
  SELECT 0 AS it, node, CASE WHEN node = {source} THEN 0::BIGINT END AS dist, node = {source} AS l, node = {source} AND {two} AS h, 0::BIGINT AS now, false AS second, false AS done,
    0::BIGINT AS messages, 0::BIGINT AS updates FROM (SELECT DISTINCT src AS node FROM b)
  UNION ALL
  SELECT * FROM (
    WITH p AS (SELECT *, coalesce({here} = now, false) AND CASE WHEN second THEN h ELSE l END AS mine FROM {name}_r WHERE NOT done),
    o AS (SELECT b.dst, min(p.dist + b.pw) AS d, count(*) AS n FROM p JOIN b ON b.src = p.node WHERE mine AND CASE WHEN second THEN {heavy} ELSE {light} END GROUP BY b.dst),
    s AS (SELECT p.* EXCLUDE (dist, l, h), coalesce(o.d < dist, o.d IS NOT NULL) AS taking, CASE WHEN taking THEN o.d ELSE dist END AS dist, o.n,
        CASE WHEN second THEN taking OR l ELSE taking OR (l AND NOT mine) END AS l, {two} AND CASE WHEN second THEN taking OR (h AND NOT mine) ELSE taking OR h END AS h FROM p LEFT JOIN o ON o.dst = p.node),
    f AS (SELECT coalesce(sum(n), 0)::BIGINT AS messages, count(*) FILTER (taking) AS updates, min(CASE WHEN l THEN {here} END) AS next_l, min(CASE WHEN l OR h THEN {here} END) AS next_any FROM s)
    SELECT it + 1, node, dist, l, h, CASE WHEN again OR to_heavy THEN now ELSE next_any END AS now, to_heavy AS second, NOT again AND NOT to_heavy AND next_any IS NULL AS done, f_messages, f_updates
    FROM (SELECT s.*, f.messages AS f_messages, f.updates AS f_updates, next_any, NOT second AND coalesce(next_l = now, false) AS again, {two} AND NOT second AND NOT again AS to_heavy FROM s, f))),
{name}_run AS MATERIALIZED (SELECT (SELECT max(it) FROM {name}_r)::BIGINT AS rounds, (SELECT sum(messages + updates)::BIGINT FROM (SELECT DISTINCT it, messages, updates FROM {name}_r)) AS work,
  (SELECT max(dist) FROM {name}_r) AS ecc, (SELECT max(dist) FROM {name}_r WHERE it = (SELECT max(it) FROM {name}_r)) AS far)"""


def sweeps(source: str, rounds: int = 3) -> str:
    """``sw{i}``: distances of farthest-node searches; ``low``: the largest eccentricity met."""
    out = []
    for i in range(rounds):
        start = source if i == 0 else f"(SELECT arg_max(node, {{'d': dist, 'v': -node}}) FROM sw{i - 1})"
        out.append(f"""sw{i}(node, dist) USING KEY (node) AS (SELECT {start}::BIGINT, 0::BIGINT
  UNION SELECT x.* FROM (SELECT b.dst AS node, min(r.dist + b.pw) AS dist FROM sw{i} r JOIN b ON b.src = r.node GROUP BY b.dst) x
    LEFT JOIN recurring.sw{i} old ON old.node = x.node WHERE old.node IS NULL OR x.dist < old.dist)""")
    top = " UNION ALL ".join(f"SELECT max(dist) AS e FROM sw{i}" for i in range(rounds))
    return ",\n".join(out) + f",\nlow AS MATERIALIZED (SELECT max(e) AS low FROM ({top}))"


def source(seed: int = 7) -> str:
    """The node that ``pick_source`` draws."""
    return f"(SELECT arg_min(src, {{'h': {h32_sql(f"'source:{seed}:' || src")}, 'v': src}}) FROM b)"
