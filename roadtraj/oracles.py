"""DuckDB SQL of the fixtures, shared by the oracle queries.

Written from the definitions, not from the engine: chained min-plus products for
shortest paths, recursion over positions for the codecs, interval joins for
interpolation.
"""

from __future__ import annotations


def network(kind: str = "nation") -> str:
    count = "(SELECT count(*) FROM nation)" if kind == "nation" else "(SELECT count(*) FROM supplier)"
    return f"""
dims AS (SELECT n, CASE n WHEN 1000 THEN 40 WHEN 100 THEN 10 ELSE 5 END AS wide FROM (SELECT {count} AS n)),
grid AS (SELECT dims.wide, n // wide AS high, CAST(v.range AS INT) AS v, v.range % wide AS x, v.range // wide AS y, d.range AS dir
  FROM dims, range(1000) v, range(4) d WHERE v.range < n),
turned AS (SELECT *, CASE dir WHEN 0 THEN (x + 1) % wide WHEN 2 THEN (x + wide - 1) % wide ELSE x END AS hx,
  CASE dir WHEN 1 THEN (y + 1) % high WHEN 3 THEN (y + high - 1) % high ELSE y END AS hy FROM grid),
net AS (SELECT CAST(v * 4 + dir AS INT) AS e, v AS tail, CAST(hy * wide + hx AS INT) AS head,
  CAST(3000 * greatest(abs(hx - x), abs(hy - y)) + ((least(v, hy * wide + hx) * 31 + greatest(v, hy * wide + hx) * 17) % 7) * 150 AS BIGINT) AS w,
  CAST(x * 3000 AS BIGINT) AS x0, CAST(y * 3000 AS BIGINT) AS y0, CAST(hx * 3000 AS BIGINT) AS x1, CAST(hy * 3000 AS BIGINT) AS y1,
  CAST(CASE WHEN dir % 2 = 0 THEN y ELSE 1000 + x END AS INT) AS street FROM turned)"""


WALK = """
ev AS (SELECT event_id, user_id, event_type, value, epoch_us(ts) AS us FROM events),
eturn AS (SELECT *, CAST((us - 1704067200000000) // 864000000000 AS INT) AS dk,
  CASE WHEN event_type = 'error' THEN NULL WHEN value < 35 THEN 0 WHEN value < 70 THEN 1 WHEN value < 110 THEN 2 ELSE 3 END AS dir FROM ev),
emove AS (SELECT *, user_id * 10 + dk AS trip_id, CASE dir WHEN 0 THEN 1 WHEN 2 THEN -1 ELSE 0 END AS dx, CASE dir WHEN 1 THEN 1 WHEN 3 THEN -1 ELSE 0 END AS dy FROM eturn),
esum AS (SELECT *, row_number() OVER (PARTITION BY trip_id ORDER BY us, event_id) AS seq,
  coalesce(sum(dx) OVER (PARTITION BY trip_id ORDER BY us, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS sx,
  coalesce(sum(dy) OVER (PARTITION BY trip_id ORDER BY us, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS sy FROM emove),
epos AS (SELECT esum.*, dims.wide, ((((user_id % n) % wide + sx) % wide) + wide) % wide AS px, ((((user_id % n) // wide + sy) % (n // wide)) + (n // wide)) % (n // wide) AS py FROM esum, dims),
walk AS (SELECT trip_id, dk, seq, event_id, CASE WHEN dir IS NOT NULL THEN CAST((py * wide + px) * 4 + dir AS INT) END AS e, us // 1300 AS t FROM epos),
steps AS (SELECT trip_id, dk = 0 AS train, row_number() OVER (PARTITION BY trip_id ORDER BY seq) AS pos, e FROM walk WHERE e IS NOT NULL),
wd AS (SELECT walk.*, w, CASE WHEN walk.e IS NOT NULL THEN coalesce(sum(w) OVER (PARTITION BY trip_id ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + w * (event_id % 4 + 1) // 4 END AS d0
  FROM walk LEFT JOIN net ON walk.e = net.e),
points AS (SELECT trip_id, seq, CAST(coalesce(max(d0) OVER (PARTITION BY trip_id ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 0) AS BIGINT) AS d, CAST(t AS BIGINT) AS t FROM wd)"""

PAIRS = """
p0 AS (SELECT u, v, min(d) AS d FROM (SELECT tail AS u, head AS v, w AS d FROM net UNION ALL SELECT DISTINCT tail, tail, 0 FROM net) GROUP BY u, v),
p1 AS (SELECT a.u, b.v, min(a.d + b.d) AS d FROM p0 a JOIN p0 b ON a.v = b.u GROUP BY a.u, b.v),
p2 AS (SELECT a.u, b.v, min(a.d + b.d) AS d FROM p1 a JOIN p1 b ON a.v = b.u GROUP BY a.u, b.v),
p3 AS (SELECT a.u, b.v, min(a.d + b.d) AS d FROM p2 a JOIN p2 b ON a.v = b.u GROUP BY a.u, b.v),
p4 AS (SELECT a.u, b.v, min(a.d + b.d) AS d FROM p3 a JOIN p3 b ON a.v = b.u GROUP BY a.u, b.v),
p5 AS (SELECT a.u, b.v, min(a.d + b.d) AS d FROM p4 a JOIN p4 b ON a.v = b.u GROUP BY a.u, b.v),
tight AS (SELECT p.u, net.head AS v, min(net.e) AS last_edge FROM p5 p JOIN net ON p.v = net.tail JOIN p5 q ON q.u = p.u AND q.v = net.head AND q.d = p.d + net.w WHERE p.u <> net.head GROUP BY p.u, net.head),
sp AS (SELECT p5.u, p5.v, CAST(p5.d AS BIGINT) AS dist, CAST(last_edge AS INT) AS last_edge FROM p5 LEFT JOIN tight ON p5.u = tight.u AND p5.v = tight.v)"""

SKIPPED = """
spe AS (SELECT a.e AS a, f.e AS f, CASE WHEN a.head = f.tail THEN a.e ELSE sp.last_edge END AS came FROM net a, net f, sp WHERE a.e <> f.e AND sp.u = a.head AND sp.v = f.tail),
long AS (SELECT trip_id, train, pos, e, lead(e) OVER (PARTITION BY trip_id ORDER BY pos) AS nxt, max(pos) OVER (PARTITION BY trip_id) AS n FROM steps),
greedy(trip_id, pos, anchor, kept) AS (
  SELECT trip_id, pos, e, TRUE FROM long WHERE pos = 1
  UNION ALL
  SELECT l.trip_id, l.pos, CASE WHEN spe.came IS DISTINCT FROM l.e THEN l.e ELSE g.anchor END, spe.came IS DISTINCT FROM l.e
  FROM greedy g JOIN long l ON l.trip_id = g.trip_id AND l.pos = g.pos + 1 LEFT JOIN spe ON spe.a = g.anchor AND spe.f = l.nxt WHERE l.nxt IS NOT NULL),
stayed AS (SELECT trip_id, pos FROM greedy WHERE kept UNION SELECT trip_id, n FROM long),
short AS (SELECT long.trip_id, train, long.pos AS place, row_number() OVER (PARTITION BY long.trip_id ORDER BY long.pos) AS pos, e FROM long JOIN stayed USING (trip_id, pos))"""

def mined(theta: int = 3, source: str = "short") -> str:
    """grams(gram, n, freq) of the training trips, and ``ahead``: the grams that end and start at each place."""
    back = ", ".join(f"lag(e, {k}) OVER t AS b{k + 1}" for k in range(1, theta))
    onward = ", ".join(f"lead(e, {k}) OVER t AS e{k + 1}" for k in range(1, theta))
    each = " UNION ALL ".join(f"SELECT {' || chr(45) || '.join(['CAST(e AS VARCHAR)', *(f'e{k}' for k in range(2, n + 1))])} AS gram, {n} AS n FROM ahead WHERE train{f' AND e{n} IS NOT NULL' if n > 1 else ''}" for n in range(1, theta + 1))
    return f"""
ahead AS (SELECT trip_id, train, pos, e{', ' + back if back else ''}{', ' + onward if onward else ''} FROM {source} WINDOW t AS (PARTITION BY trip_id ORDER BY pos)),
counted AS (SELECT gram, n, count(*) AS freq FROM ({each}) GROUP BY gram, n),
grams AS (SELECT gram, n, freq FROM counted UNION ALL SELECT CAST(e AS VARCHAR), 1, 0 FROM net WHERE CAST(e AS VARCHAR) NOT IN (SELECT gram FROM counted))"""


# Code lengths: the two least weights are merged until one is left; of equals leaves come first, then what was merged first.
CODED = """
leaf AS (SELECT gram, n, freq, row_number() OVER (ORDER BY freq, n DESC, gram) AS id, count(*) OVER () AS total FROM grams),
merged(k, q, a, b) AS (
  SELECT CAST(0 AS BIGINT), (SELECT list(struct_pack(w := CAST(freq AS HUGEINT), j := 0, id := id) ORDER BY id) FROM leaf), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT)
  UNION ALL
  SELECT k + 1, list_sort(list_append(q[3:], struct_pack(w := q[1].w + q[2].w, j := 1, id := k + 1 + (SELECT max(total) FROM leaf)))), q[1].id, q[2].id FROM merged WHERE len(q) > 1),
child AS (SELECT k + (SELECT max(total) FROM leaf) AS parent, unnest([a, b]) AS id FROM merged WHERE k > 0),
depths(id, depth) AS (SELECT max(parent), 0 FROM child UNION ALL SELECT child.id, depth + 1 FROM depths JOIN child ON depths.id = child.parent),
lens AS (SELECT gram, leaf.n, freq, CAST(depth AS BIGINT) AS len FROM leaf JOIN depths ON leaf.id = depths.id)"""

# Pieces of three tilings, with their code lengths: from the end, from the front, and of least cost.
TILED = """
ending AS (SELECT a.trip_id, a.pos, l1.len AS c1, l2.len AS c2, l3.len AS c3 FROM ahead a JOIN lens l1 ON l1.gram = CAST(a.e AS VARCHAR)
  LEFT JOIN lens l2 ON l2.gram = a.b2 || '-' || a.e LEFT JOIN lens l3 ON l3.gram = a.b3 || '-' || a.b2 || '-' || a.e),
lengths AS (SELECT trip_id, pos, CASE WHEN c3 IS NOT NULL THEN 3 WHEN c2 IS NOT NULL THEN 2 ELSE 1 END AS len, coalesce(c3, c2, c1) AS bits FROM ending),
tiles(trip_id, pos, len, bits) AS (
  SELECT trip_id, pos, len, bits FROM lengths l WHERE pos = (SELECT max(pos) FROM lengths m WHERE m.trip_id = l.trip_id)
  UNION ALL
  SELECT l.trip_id, l.pos, l.len, l.bits FROM tiles t JOIN lengths l ON l.trip_id = t.trip_id AND l.pos = t.pos - t.len),
starting AS (SELECT a.trip_id, a.pos, CASE WHEN l3.len IS NOT NULL THEN 3 WHEN l2.len IS NOT NULL THEN 2 ELSE 1 END AS len, coalesce(l3.len, l2.len, l1.len) AS bits
  FROM ahead a JOIN lens l1 ON l1.gram = CAST(a.e AS VARCHAR) LEFT JOIN lens l2 ON l2.gram = a.e || '-' || a.e2 LEFT JOIN lens l3 ON l3.gram = a.e || '-' || a.e2 || '-' || a.e3),
fronts(trip_id, pos, len, bits) AS (
  SELECT trip_id, pos, len, bits FROM starting WHERE pos = 1
  UNION ALL
  SELECT s.trip_id, s.pos, s.len, s.bits FROM fronts f JOIN starting s ON s.trip_id = f.trip_id AND s.pos = f.pos + f.len),
least_cost(trip_id, pos, d0, d1, d2) AS (
  SELECT trip_id, pos, c1, CAST(0 AS BIGINT), CAST(NULL AS BIGINT) FROM ending WHERE pos = 1
  UNION ALL
  SELECT e.trip_id, e.pos, least(d0 + c1, d1 + c2, d2 + c3), d0, d1 FROM least_cost c JOIN ending e ON e.trip_id = c.trip_id AND e.pos = c.pos + 1)"""

# Pieces and the hops between them as stretches of the trip: distances at their ends.
PIECES = """
piece AS (SELECT t.trip_id, a.place AS first, b.place AS last FROM tiles t JOIN short a ON a.trip_id = t.trip_id AND a.pos = t.pos - t.len + 1 JOIN short b ON b.trip_id = t.trip_id AND b.pos = t.pos),
stretch AS (SELECT trip_id, first, last FROM piece UNION ALL SELECT trip_id, was + 1, first - 1 FROM (SELECT *, lag(last) OVER (PARTITION BY trip_id ORDER BY first) AS was FROM piece) WHERE first > was + 1),
spanned AS MATERIALIZED (SELECT s.trip_id, a.c0, b.c1 FROM stretch s JOIN cum a ON a.trip_id = s.trip_id AND a.pos = s.first JOIN cum b ON b.trip_id = s.trip_id AND b.pos = s.last)"""

GRAMS = """
ahead AS (SELECT trip_id, train, pos, e, lead(e) OVER t AS e2, lead(e, 2) OVER t AS e3, lag(e) OVER t AS b2, lag(e, 2) OVER t AS b3 FROM short WINDOW t AS (PARTITION BY trip_id ORDER BY pos)),
counted AS (SELECT gram, n, count(*) AS freq FROM (
  SELECT CAST(e AS VARCHAR) AS gram, 1 AS n FROM ahead WHERE train UNION ALL SELECT e || '-' || e2, 2 FROM ahead WHERE train AND e2 IS NOT NULL
  UNION ALL SELECT e || '-' || e2 || '-' || e3, 3 FROM ahead WHERE train AND e3 IS NOT NULL) GROUP BY gram, n),
grams AS (SELECT gram, n, freq FROM counted UNION ALL SELECT CAST(e AS VARCHAR), 1, 0 FROM net WHERE CAST(e AS VARCHAR) NOT IN (SELECT gram FROM counted))"""

LENGTHS = """
lengths AS (SELECT trip_id, pos, CASE WHEN b3 || '-' || b2 || '-' || e IN (SELECT gram FROM grams) THEN 3 WHEN b2 || '-' || e IN (SELECT gram FROM grams) THEN 2 ELSE 1 END AS len FROM ahead),
tiles(trip_id, pos, len) AS (
  SELECT trip_id, pos, len FROM lengths l WHERE pos = (SELECT max(pos) FROM lengths m WHERE m.trip_id = l.trip_id)
  UNION ALL
  SELECT l.trip_id, l.pos, l.len FROM tiles t JOIN lengths l ON l.trip_id = t.trip_id AND l.pos = t.pos - t.len)"""


def thinned(tau: int | str, eta: int | str, source: str = "points") -> str:
    """kept(trip_id, seq): the points of the angular codec, by recursion with fractions as pairs.

    Bounds are numbers, or the columns tau and eta of the source.
    """
    own, inner, outer = (", tau, eta", ", q.tau, q.eta", ", p.tau, p.eta") if isinstance(tau, str) else ("", "", "")
    return f"""
pts AS (SELECT trip_id, seq, CAST(d AS HUGEINT) AS d, CAST(t AS HUGEINT) AS t, max(seq) OVER (PARTITION BY trip_id) AS n{own} FROM {source}),
run(trip_id, seq, kept, ad, aat, pd, pt, ln, lm, hn, hm) AS (
  SELECT trip_id, seq, CAST(NULL AS BIGINT), d, t, d, t, CAST(0 AS HUGEINT), CAST(1 AS HUGEINT), CAST(1 AS HUGEINT), CAST(0 AS HUGEINT) FROM pts WHERE seq = 1
  UNION ALL
  SELECT trip_id, seq, kept, ad, aat, d, t,
    CASE WHEN l2n * l1m > l1n * l2m THEN l2n ELSE l1n END, CASE WHEN l2n * l1m > l1n * l2m THEN l2m ELSE l1m END,
    CASE WHEN h2n * h1m < h1n * h2m THEN h2n ELSE h1n END, CASE WHEN h2n * h1m < h1n * h2m THEN h2m ELSE h1m END
  FROM (SELECT *, CASE WHEN (d - ad - {tau}) * lm > ln * (t - aat) THEN d - ad - {tau} ELSE ln END AS l1n, CASE WHEN (d - ad - {tau}) * lm > ln * (t - aat) THEN t - aat ELSE lm END AS l1m,
      d - ad AS l2n, t - aat + {eta} AS l2m,
      CASE WHEN (d - ad + {tau}) * hm < hn * (t - aat) THEN d - ad + {tau} ELSE hn END AS h1n, CASE WHEN (d - ad + {tau}) * hm < hn * (t - aat) THEN t - aat ELSE hm END AS h1m,
      CASE WHEN t - aat > {eta} THEN d - ad ELSE 1 END AS h2n, CASE WHEN t - aat > {eta} THEN t - aat - {eta} ELSE 0 END AS h2m
    FROM (SELECT p.trip_id, p.seq, p.d, p.t{outer}, CASE WHEN ok THEN NULL ELSE r_seq END AS kept, CASE WHEN ok THEN ad0 ELSE pd0 END AS ad, CASE WHEN ok THEN at0 ELSE pt0 END AS aat,
        CASE WHEN ok THEN ln0 ELSE 0 END AS ln, CASE WHEN ok THEN lm0 ELSE 1 END AS lm, CASE WHEN ok THEN hn0 ELSE 1 END AS hn, CASE WHEN ok THEN hm0 ELSE 0 END AS hm
      FROM (SELECT q.trip_id, q.seq, q.d, q.t{inner}, r.seq AS r_seq, r.ad AS ad0, r.aat AS at0, r.pd AS pd0, r.pt AS pt0, r.ln AS ln0, r.lm AS lm0, r.hn AS hn0, r.hm AS hm0,
          (q.d - r.ad) * r.lm >= r.ln * (q.t - r.aat) AND (q.d - r.ad) * r.hm <= r.hn * (q.t - r.aat) AS ok
        FROM run r JOIN pts q ON q.trip_id = r.trip_id AND q.seq = r.seq + 1) p) s) z),
kept AS (SELECT trip_id, kept AS seq FROM run WHERE kept IS NOT NULL UNION SELECT trip_id, 1 FROM pts WHERE seq = 1 UNION SELECT trip_id, n FROM pts WHERE seq = n)"""


SEGMENTS = """
segs AS (SELECT trip_id, d AS d0, t AS t0, lead(d) OVER s AS d1, lead(t) OVER s AS t1, row_number() OVER s AS i FROM {source} WINDOW s AS (PARTITION BY trip_id ORDER BY t)),
ends AS (SELECT trip_id, min(t) AS t_first, max(t) AS t_last, min(d) AS d_first, max(d) AS d_last FROM {source} GROUP BY trip_id)"""

CUM = """
cum AS (SELECT trip_id, pos, steps.e, w, x0, y0, x1, y1, sum(w) OVER c - w AS c0, sum(w) OVER c AS c1, sum(w) OVER (PARTITION BY trip_id) AS total FROM steps JOIN net ON steps.e = net.e WINDOW c AS (PARTITION BY trip_id ORDER BY pos))"""


def at_time(asked: str, key: str = "t") -> str:
    """SELECT of all columns of ``asked`` and d at its time, from segs and ends."""
    return f"""SELECT a.*, CAST(CASE WHEN a.{key} <= t_first THEN d_first WHEN a.{key} >= t_last THEN d_last ELSE d0 + (d1 - d0) * (a.{key} - t0) // (t1 - t0) END AS BIGINT) AS d
  FROM {asked} a JOIN ends ON a.trip_id = ends.trip_id LEFT JOIN segs ON segs.trip_id = a.trip_id AND segs.t0 < a.{key} AND a.{key} <= segs.t1"""


def at_distance(asked: str, key: str = "d") -> str:
    """SELECT of all columns of ``asked`` and the earliest time at its distance, from segs and ends."""
    return f"""SELECT a.*, CAST(CASE WHEN a.{key} <= d_first THEN t_first WHEN a.{key} > d_last THEN t_last ELSE t0 + (t1 - t0) * (a.{key} - d0) // (d1 - d0) END AS BIGINT) AS t_at
  FROM {asked} a JOIN ends ON a.trip_id = ends.trip_id LEFT JOIN segs ON segs.trip_id = a.trip_id AND segs.d0 < a.{key} AND a.{key} <= segs.d1"""
