"""SQL twins of the buffered multilevel method: recursive queries that walk the vertices in the order of the method.

Clusters of all buffers come from one recursion a level (buffers do not touch each other in it), coarse vertices and edges
from plain grouping, and a last recursion walks a schedule: for each buffer its coarsest vertices, local search on each
level down to the finest, commit. It carries the blocks of all vertices of all levels and the loads as lists. The twins
share no code with the engine but the text of the keyed mixer.
"""

from __future__ import annotations

from cutstream.functions.columns import mix31_sql


def _clusters(i: int, rounds: int, seed: int, tie: str, lmax_share: int, again: bool) -> str:
    """Levels i to i + 1: labels by recursion, then the next level's vertices (n), half-edges (h) and map (m).

    again: votes come from vertices of the same block of the pass before (o).
    """
    if tie == "random":  # the keyed number of the round
        keys = [mix31_sql("CAST((u - low) * 1000003 + (x - low) AS BIGINT)", seed + i + 131 * r, "duckdb") for r in range(rounds)]
        key = "CASE turn " + " ".join(f"WHEN {r} THEN {k}" for r, k in enumerate(keys)) + " END"
    else:
        key = "x"
    same = f" JOIN o{i} oa ON oa.id = src JOIN o{i} ob ON ob.id = dst WHERE oa.block = ob.block" if again else ""
    up = f",\no{i + 1} AS (SELECT m{i}.up AS id, any_value(o{i}.block) AS block FROM m{i} JOIN o{i} USING (id) GROUP BY m{i}.up)" if again else ""
    votes = "coalesce(list_sum(list_transform(list_filter(ns, lambda y: labels[y.o + 1] = x), lambda y: y.w)), 0.0)"
    options = "list_distinct(list_append(list_transform(ns, lambda y: labels[y.o + 1]), now))"
    pick = f"list_sort(list_transform(list_filter({options}, lambda x: x = now OR sizes[x + 1] + c <= most), lambda x: {{'v': -{votes}, 'r': {key}, 'x': x}}))[1].x"
    return f"""
lim{i} AS (SELECT n{i}.buf, min(n{i}.id) AS low, count(*) AS cnt, greatest(max(n{i}.w), (SELECT lmax FROM lim) / {lmax_share}) AS most FROM n{i} GROUP BY n{i}.buf),
go{i} AS (SELECT lim{i}.*, has{i}.on AND cnt > 1 AND cnt >= has{i}.stop AS going FROM lim{i} JOIN has{i} USING (buf)),
nb{i} AS (SELECT src AS id, list({{'o': dst, 'w': w}} ORDER BY dst) AS ns FROM h{i}{same} GROUP BY src),
st{i} AS MATERIALIZED (SELECT n{i}.id, n{i}.buf, n{i}.w AS c, go{i}.low, most, going, coalesce(ns, []) AS ns FROM n{i} JOIN go{i} USING (buf) LEFT JOIN nb{i} USING (id)),
lp{i}(step, labels, sizes, moved) AS (
  SELECT CAST(0 AS BIGINT), (SELECT list(CAST(id AS BIGINT) ORDER BY id) FROM n{i}), (SELECT list(CAST(w AS DOUBLE) ORDER BY id) FROM n{i}), CAST(list_transform(range((SELECT (max(buf) + 1) * {rounds + 1} FROM n{i})), lambda z: 0) AS INTEGER[])
  UNION ALL
  SELECT step + 1, CASE WHEN best = now THEN labels ELSE list_concat(list_concat(labels[1:u], [best]), labels[u + 2:]) END,
    CASE WHEN best = now THEN sizes ELSE list_transform(range(len(sizes)), lambda z: sizes[z + 1] + CASE WHEN z = best THEN c WHEN z = now THEN -c ELSE 0.0 END) END,
    CASE WHEN best = now THEN moved ELSE list_transform(range(len(moved)), lambda z: CASE WHEN z = flag THEN 1 ELSE moved[z + 1] END) END
  FROM (SELECT step, labels, sizes, moved, u, c, now, turn, buf * {rounds + 1} + turn AS flag,
      CASE WHEN going AND len(ns) > 0 AND (turn = 0 OR moved[buf * {rounds + 1} + turn] = 1) THEN {pick} ELSE now END AS best
    FROM (SELECT q.*, s.id AS u, s.buf, s.c, s.low, s.most, s.going, s.ns, q.labels[s.id + 1] AS now FROM (SELECT *, step // len(labels) AS turn FROM lp{i} WHERE step < {rounds} * len(labels)) q JOIN st{i} s ON s.id = q.step % len(q.labels)))),
lab{i} AS (SELECT id - 1 AS id, label FROM (SELECT unnest(labels) AS label, unnest(range(1, len(labels) + 1)) AS id FROM lp{i} WHERE step = {rounds} * len(labels))),
ok{i} AS (SELECT buf, any_value(going) AND count(DISTINCT label) <= 0.95 * count(*) AS ok FROM n{i} JOIN lab{i} USING (id) JOIN go{i} USING (buf) GROUP BY buf),
m{i} AS (SELECT id, buf, dense_rank() OVER (ORDER BY CASE WHEN ok THEN label ELSE id END) - 1 AS up FROM n{i} JOIN lab{i} USING (id) JOIN ok{i} USING (buf)),
n{i + 1} AS (SELECT m{i}.up AS id, any_value(n{i}.buf) AS buf, sum(n{i}.w) AS w FROM m{i} JOIN n{i} USING (id) GROUP BY m{i}.up),
h{i + 1} AS (SELECT a.up AS src, b.up AS dst, sum(h.w) AS w FROM h{i} h JOIN m{i} a ON a.id = h.src JOIN m{i} b ON b.id = h.dst WHERE a.up <> b.up GROUP BY 1, 2),
has{i + 1} AS (SELECT buf, has{i}.stop, ok AS on FROM has{i} JOIN ok{i} USING (buf)){up}"""


def multilevel_sql(cte: str, k: int, delta: str, model: str = "extended", objective: str = "penalty_gain", eps: str = "1.03", x: int = 4, rounds: int = 5, refine: int = 5, seed: int = 42, tie: str = "random", share: int = 14, levels: int = 4, after: str | None = None) -> str:
    """(pos, block) of one pass over unit-weight vertices. cte: v(pos) and g(src, dst, weight). delta: a SQL expression over
    n, the number of vertices. levels: an upper bound of coarser levels. after: the query of the pass before, which this
    one replays."""
    again = after is not None
    ghosts = model == "extended" and not again
    mixed = mix31_sql("CAST(dst * 1000003 + src AS BIGINT)", seed, "duckdb")
    q = "1.5 * (sqrt(CAST({k} AS DOUBLE)) * (SELECT count(*) FROM g) / ((SELECT count(*) FROM v) * sqrt(CAST((SELECT count(*) FROM v) AS DOUBLE))))".replace("{k}", str(k))
    parts = [f"""sz AS (SELECT n, {delta} AS delta FROM (SELECT count(*) AS n FROM v)),
lim AS (SELECT CAST(ceil(CAST({eps} AS DECIMAL(9, 4)) * n / {k}) AS DOUBLE) AS lmax, {q} AS q FROM sz),
c AS (SELECT src, dst, weight AS w, src // delta AS a, dst // delta AS b FROM g, sz),
rep AS (SELECT a, dst, arg_min(src, {mixed} * 1000000 + src) AS rep FROM c WHERE a <> b GROUP BY a, dst),
gw AS (SELECT rep AS pos, count(*) AS n FROM rep GROUP BY rep),
inner_edges AS (SELECT src, dst, w FROM c WHERE a = b{" UNION ALL SELECT r.rep, c.src, c.w / 2 FROM c JOIN rep r ON r.a = c.a AND r.dst = c.dst WHERE c.a <> c.b AND r.rep <> c.src" if ghosts else ""}),
h0 AS (SELECT src, dst, sum(w) AS w FROM (SELECT src, dst, w FROM inner_edges UNION ALL SELECT dst, src, w FROM inner_edges) GROUP BY 1, 2),
n0 AS (SELECT v.pos AS id, v.pos // delta AS buf, CAST(1 + {"coalesce(gw.n, 0)" if ghosts else "0"} AS DOUBLE) AS w FROM v CROSS JOIN sz LEFT JOIN gw ON gw.pos = v.pos),
has0 AS (SELECT buf, greatest((count(*) + {k}) / {2 * x * k}.0, {x * k}) AS stop, true AS on FROM n0 GROUP BY buf)"""]
    if again:
        parts.append(f"prev AS MATERIALIZED ({after}), o0 AS (SELECT pos AS id, block FROM prev)")
    parts += [_clusters(i, rounds, seed, tie, share, again) for i in range(levels)]
    parts.append(f"off AS (SELECT level, CAST(coalesce(sum(n) OVER (ORDER BY level ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS low FROM ({' UNION ALL '.join(f'SELECT {i} AS level, (SELECT count(*) FROM n{i}) AS n' for i in range(levels + 1))}))")
    low = lambda i: f"(SELECT low FROM off WHERE level = {i})"
    # Edges of every level in flat places: to vertices of the level and, for members, to earlier buffers' vertices.
    parts.append(f"x0 AS (SELECT dst AS id, src AS o, w FROM c WHERE a <> b{' UNION ALL SELECT src, dst, w FROM c WHERE a <> b' if again else ''})")
    parts += [f"x{i + 1} AS (SELECT m.up AS id, x.o, x.w FROM x{i} x JOIN m{i} m USING (id))" for i in range(levels)]
    near = " UNION ALL ".join(f"SELECT {i} AS level, src AS id, CAST(dst + {low(i)} AS BIGINT) AS o, w FROM h{i} UNION ALL SELECT {i}, id, o, w FROM x{i}" for i in range(levels + 1))
    parts.append(f"near AS (SELECT level, id, list({{'o': o, 'w': CAST(w AS DOUBLE)}} ORDER BY o, w) AS ns FROM ({near}) GROUP BY level, id)")
    every = " UNION ALL ".join(f"SELECT {i} AS level, n.id, n.buf, n.w, {low(i)} AS low FROM n{i} n JOIN has{i} USING (buf) WHERE has{i}.on" for i in range(levels + 1))
    parts.append(f"vx AS (SELECT * FROM ({every}))")
    copies = " UNION ALL ".join(f"SELECT m.buf, {i} AS level, min(m.id) + {low(i)} AS f, max(m.id) + {low(i)} + 1 AS t, list({{'o': CAST(m.up + {low(i + 1)} AS BIGINT), 'w': CAST(0 AS DOUBLE)}} ORDER BY m.id) AS ns FROM m{i} m JOIN has{i + 1} USING (buf) WHERE has{i + 1}.on GROUP BY m.buf" for i in range(levels))
    parts.append(f"copies AS ({copies})")
    lifted = " UNION ALL ".join(f"SELECT buf, {i + 1} AS level, min(up) + {low(i + 1)} AS f, max(up) + {low(i + 1)} + 1 AS t, list({{'o': CAST(o AS BIGINT), 'w': CAST(0 AS DOUBLE)}} ORDER BY up) AS ns FROM (SELECT m.buf, m.up, min(m.id) + {low(i)} AS o FROM m{i} m JOIN has{i + 1} USING (buf) WHERE has{i + 1}.on GROUP BY m.buf, m.up) GROUP BY buf" for i in range(levels))
    lift = " UNION ALL SELECT buf, CAST(-1 AS INTEGER), level, 0, 'copy', f, t, 0.0, ns FROM lifted" if again else ""
    parts.append(f"lifted AS ({lifted})")
    parts.append(f"""todo AS (
  SELECT buf, CAST(-1 AS INTEGER) AS phase, 0 AS turn, CAST(0 AS BIGINT) AS id, 'begin' AS kind, min(id) AS f, max(id) + 1 AS t, 0.0 AS c, [] AS ns FROM n0 GROUP BY buf{lift}
  UNION ALL SELECT buf, ({levels} - level) * 2, 0, 0, 'copy', f, t, 0.0, ns FROM copies
  UNION ALL SELECT vx.buf, ({levels} - level) * 2 + 1, turn, vx.id, CASE WHEN turn = 0 THEN 'place' ELSE 'refine' END, CAST(vx.id + vx.low AS BIGINT), 0, CAST(vx.w AS DOUBLE), coalesce(near.ns, []) FROM vx CROSS JOIN (SELECT unnest(range({refine + 1})) AS turn) LEFT JOIN near USING (level, id)
  UNION ALL SELECT buf, {2 * levels + 2}, 0, id, 'last', id, 0, CAST(w AS DOUBLE), [] FROM n0
  UNION ALL SELECT buf, {2 * levels + 3}, 0, 0, 'commit', min(id), max(id) + 1, 0.0, [] FROM n0 GROUP BY buf),
plan AS MATERIALIZED (SELECT row_number() OVER (ORDER BY buf, phase, turn, id) - 1 AS step, kind, f, t, c, ns FROM todo)""")
    penalty = "CASE WHEN l <= 0 THEN 0.0 ELSE q * sqrt(l) END"
    score = f"conn - c * ({penalty})" if objective == "penalty_gain" else "conn * (1 - l / lmax)"
    conn = "coalesce(list_sum(list_transform(list_filter(ns, lambda y: out[y.o + 1] = i), lambda y: y.w)), 0.0)"
    scored = f"list_transform(list_transform(range({k}), lambda i: {{'i': i, 'conn': {conn}, 'l': loads[i + 1] - CASE WHEN i = now THEN c ELSE 0.0 END}}), lambda z: {{'s': -({score.replace('conn', 'z.conn').replace('lmax', '§').replace('l <=', 'z.l <=').replace('sqrt(l)', 'sqrt(z.l)').replace('- l /', '- z.l /').replace('§', 'lmax')}), 'away': z.i <> now, 'l': z.l, 'i': z.i, 'conn': z.conn}})"
    best = f"list_sort(list_filter({scored}, lambda z: (z.i = now) OR (z.l + c <= lmax AND (kind = 'place' OR z.conn > 0))))"
    place = f"list_sort(list_transform(list_filter({scored}, lambda z: z.l + c <= lmax), lambda z: {{'s': z.s, 'l': z.l, 'i': z.i}}))"
    empty = f"CAST(list_transform(range({k}), lambda z: 0.0) AS DOUBLE[])"
    places = f"CAST(list_transform(range((SELECT CAST(sum(n) AS BIGINT) FROM ({' UNION ALL '.join(f'SELECT count(*) AS n FROM n{i}' for i in range(1 if again else 0, levels + 1))}))), lambda z: -1) AS INTEGER[])"
    start, held = places, empty
    if again:
        start = f"list_concat((SELECT list(block ORDER BY pos) FROM prev), {places})"
        held = f"(SELECT CAST(list_transform(range({k}), lambda i: len(list_filter(bs, lambda z: z = i))) AS DOUBLE[]) FROM (SELECT list(block) AS bs FROM prev))"
    own = "list_transform(range({k}), lambda i: base[i + 1] {sign} len(list_filter(out[f + 1:t], lambda z: z = i)))".replace("{k}", str(k))
    parts.append(f"""walk(step, out, loads, base) AS (
  SELECT CAST(0 AS BIGINT), {start}, {empty}, {held}
  UNION ALL
  SELECT step + 1,
    CASE WHEN kind = 'copy' THEN list_concat(list_concat(out[1:f], list_transform(ns, lambda y: out[y.o + 1])), out[t + 1:]) WHEN new = now OR kind IN ('begin', 'commit') THEN out ELSE list_concat(list_concat(out[1:f], [new]), out[f + 2:]) END,
    CASE WHEN kind = 'begin' THEN base WHEN kind IN ('copy', 'commit') OR new = now THEN loads ELSE list_transform(range({k}), lambda i: loads[i + 1] + CASE WHEN i = new THEN c WHEN i = now THEN -c ELSE 0.0 END) END,
    CASE WHEN kind = 'commit' THEN {own.replace('{sign}', '+')} WHEN kind = 'begin' AND {str(again).lower()} THEN {own.replace('{sign}', '-')} ELSE base END
  FROM (SELECT *, CAST(CASE
      WHEN kind = 'place' AND now < 0 THEN coalesce({place}[1].i, -1)
      WHEN kind = 'refine' AND now >= 0 THEN {best}[1].i
      WHEN kind = 'last' AND now < 0 THEN list_sort(list_transform(range({k}), lambda i: {{'l': loads[i + 1], 'i': i}}))[1].i
      ELSE now END AS INTEGER) AS new
    FROM (SELECT w.*, p.kind, p.f, p.t, p.c, p.ns, CASE WHEN p.kind IN ('place', 'refine', 'last') THEN w.out[p.f + 1] ELSE 0 END AS now, lim.q, lim.lmax FROM lim, walk w JOIN plan p ON p.step = w.step)))""")
    parts.append(f"final AS (SELECT out FROM walk WHERE step = (SELECT count(*) FROM plan)), res AS (SELECT CAST(i AS BIGINT) AS pos, out[i + 1] AS block FROM (SELECT out, unnest(range((SELECT count(*) FROM v))) AS i FROM final))")
    return f"WITH RECURSIVE {cte}, " + ",\n".join(parts) + "\nSELECT pos, block FROM res"
