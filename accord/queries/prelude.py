"""DuckDB SQL that oracle queries start from: the carriers in tall form, sector groups, weights and patterns, written anew in SQL."""

from __future__ import annotations


def face(rotations: int = 16) -> str:
    return f"""
lmk AS (SELECT lm, CASE WHEN lm < 5 THEN 0 WHEN lm < 10 THEN 1 WHEN lm < 14 THEN 2 WHEN lm < 19 THEN 3 WHEN lm < 25 THEN 4 WHEN lm < 31 THEN 5
  WHEN lm < 38 THEN 6 WHEN lm < 43 THEN 7 WHEN lm < 48 THEN 6 ELSE 7 END AS comp FROM range(51) g(lm)),
f0 AS (SELECT vec_id AS v, embedding AS e, label, r, label % 5 AS rule, CASE WHEN md5(vec_id::VARCHAR)[1:1] < '8' THEN 'a' ELSE 'b' END AS half FROM embeddings, range({rotations}) g(r)),
f1 AS (SELECT *, concat_ws('-', label, r, half) AS video_id, CASE WHEN label = 0 THEN 'R' WHEN label = 5 THEN 'R2' ELSE ['R', 'A', 'B', 'C', 'D'][label % 5 + 1] END AS source,
  CASE WHEN label % 5 = 0 THEN 0 ELSE 1 END AS y, (row_number() OVER (PARTITION BY label, r, half ORDER BY v) - 1)::INT AS t FROM f0),
f2 AS (SELECT f1.*, lm, comp, (131 * v + 17 * r + 7919 * lm) % 1000 < [0, 200, 150, 80, 50][rule + 1] AS loose, (17 * v + 29 * r) % 100 < [0, 50, 40, 25, 15][rule + 1] AS lips FROM f1, lmk),
f3 AS (SELECT *, CASE WHEN loose THEN (comp + 1 + (lm + v) % 7) % 8 WHEN comp = 7 THEN 6 ELSE comp - comp % 2 END AS z, CASE WHEN NOT loose AND comp = 7 AND NOT lips THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END AS sg FROM f2),
face AS (SELECT video_id, source, y, half, t, lm::INT AS lm,
  round(1000 * (8 * (0.3::DOUBLE * e[(16 + 4 * r) % 64 + 1]::DOUBLE + sg * e[(2 * z + 4 * r) % 64 + 1]::DOUBLE + 0.5::DOUBLE * e[(18 + 2 * lm % 46 + 4 * r) % 64 + 1]::DOUBLE)))::BIGINT AS dx_m,
  round(1000 * (8 * (0.3::DOUBLE * e[(17 + 4 * r) % 64 + 1]::DOUBLE + sg * e[(2 * z + 1 + 4 * r) % 64 + 1]::DOUBLE + 0.5::DOUBLE * e[(19 + 2 * lm % 46 + 4 * r) % 64 + 1]::DOUBLE)))::BIGINT AS dy_m FROM f3)"""


#: Pairs with enough motion (half of the magnitudes at 0.85 or more), in the hash order of their pools.
STRONG = """
strong AS (SELECT video_id, t, any_value(source) AS source, any_value(y) AS y, any_value(half) AS half FROM face GROUP BY video_id, t
  HAVING count(*) FILTER (dx_m * dx_m + dy_m * dy_m >= 722500) >= 0.5 * count(*))"""


def picked(n: int, pool: str = "video_id", seed: int = 0, short: str = "keep") -> str:
    """Pairs of strong, the first n of each pool."""
    return f"""
ranked AS (SELECT *, row_number() OVER (PARTITION BY {pool} ORDER BY md5(concat_ws(':', '{seed}', video_id, t)), video_id, t) AS pick, count(*) OVER (PARTITION BY {pool}) AS in_pool FROM strong),
picked AS (SELECT * FROM ranked WHERE pick <= {n} {"AND in_pool >= " + str(n) if short == "drop" else ""})"""


def sectors(k: int = 6, of: str = "face JOIN picked USING (video_id, t)") -> str:
    """lab: each landmark's sector; grp: a pair's groups, score and weight in thousandths."""
    return f"""
lab AS (SELECT video_id, t, lm, dx_m, dy_m, least(floor((atan2(dy_m::DOUBLE, dx_m::DOUBLE) + pi()) / (2 * pi() / {k})), {k} - 1)::INT AS c FROM {of}),
own AS (SELECT video_id, t, c, count(*)::BIGINT AS n, sum(dx_m)::BIGINT AS sx, sum(dy_m)::BIGINT AS sy, sum(dx_m * dx_m + dy_m * dy_m)::BIGINT AS q FROM lab GROUP BY video_id, t, c),
sc AS (SELECT video_id, t, count(*)::INT AS k_found, sum(n)::BIGINT AS n, sum((sx * sx + sy * sy)::DOUBLE / n) AS g, ((sum(sx) * sum(sx) + sum(sy) * sum(sy))::DOUBLE / sum(n)) AS w, sum(q)::DOUBLE AS q FROM own GROUP BY video_id, t),
grp AS (SELECT video_id, t, k_found, n, g - w AS b, q - g AS i, CASE WHEN k_found > 1 AND q - g <> 0 THEN (g - w) / (q - g) * (n - k_found) / (k_found - 1) ELSE 0 END AS score FROM sc),
wgt AS (SELECT video_id, t, k_found, score, round(1000 * (k_found * score))::BIGINT AS w FROM grp)"""


def pattern(by: str, keys: str = "picked") -> str:
    """cell: tall pattern sums by columns of `keys`; tot: sums of weights; pat: with p = w over the sum of all cells."""
    return f"""
cell AS (SELECT {by}, a.lm AS i, b.lm AS j, sum(w)::BIGINT AS w FROM lab a JOIN lab b ON a.video_id = b.video_id AND a.t = b.t AND a.lm > b.lm AND a.c = b.c
  JOIN wgt g ON g.video_id = a.video_id AND g.t = a.t JOIN (SELECT video_id, t, * EXCLUDE (video_id, t) FROM {keys}) k ON k.video_id = a.video_id AND k.t = a.t GROUP BY ALL),
tot AS (SELECT {by}, sum(w)::BIGINT AS w_sum, count(*) AS n_pairs FROM wgt g JOIN (SELECT video_id, t, * EXCLUDE (video_id, t) FROM {keys}) k ON k.video_id = g.video_id AND k.t = g.t GROUP BY ALL)"""


#: Motion of events and of line items in thousandths, as in the carriers.
EVT = """
pos AS (SELECT user_id::VARCHAR AS video_id, floor(date_diff('day', DATE '2024-01-01', ts::DATE) / 3)::INT AS t, (list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1)::INT AS lm,
  avg(value) AS px, avg((props->>'$.k')::DOUBLE) AS py FROM events GROUP BY ALL),
frm AS (SELECT DISTINCT video_id, t FROM pos),
prs AS (SELECT a.video_id, a.t FROM frm a JOIN frm b ON a.video_id = b.video_id AND b.t = a.t + 1),
evt AS (SELECT p.video_id, p.t, l.lm::INT AS lm, coalesce(round(1000 * (b.px - a.px)), 0)::BIGINT AS dx_m, coalesce(round(1000 * (b.py - a.py)), 0)::BIGINT AS dy_m
  FROM prs p CROSS JOIN range(5) l(lm) LEFT JOIN pos a ON a.video_id = p.video_id AND a.t = p.t AND a.lm = l.lm LEFT JOIN pos b ON b.video_id = p.video_id AND b.t = p.t + 1 AND b.lm = l.lm)"""

LI = """
pos AS (SELECT l_suppkey::VARCHAR AS video_id, ((year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1)::INT AS t, (l_linenumber - 1)::INT AS lm, avg(l_quantity) AS px, avg(100 * l_discount) AS py FROM lineitem GROUP BY ALL),
frm AS (SELECT DISTINCT video_id, t FROM pos),
prs AS (SELECT a.video_id, a.t FROM frm a JOIN frm b ON a.video_id = b.video_id AND b.t = a.t + 1),
li AS (SELECT p.video_id, p.t, l.lm::INT AS lm, coalesce(round(1000 * (b.px - a.px)), 0)::BIGINT AS dx_m, coalesce(round(1000 * (b.py - a.py)), 0)::BIGINT AS dy_m
  FROM prs p CROSS JOIN range(7) l(lm) LEFT JOIN pos a ON a.video_id = p.video_id AND a.t = p.t AND a.lm = l.lm LEFT JOIN pos b ON b.video_id = p.video_id AND b.t = p.t + 1 AND b.lm = l.lm)"""

IMG = """
cel AS (SELECT r_name AS video_id, ((year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1)::INT AS t, floor((l_quantity - 1) / 5)::INT AS x, round(100 * l_discount)::INT AS y, sum(l_quantity)::DOUBLE AS i
  FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL),
img AS (SELECT f.video_id, f.t, gx.x::INT AS x, gy.y::INT AS y, coalesce(c.i, 0) AS i FROM (SELECT DISTINCT video_id, t FROM cel) f CROSS JOIN range(10) gx(x) CROSS JOIN range(11) gy(y)
  LEFT JOIN cel c ON c.video_id = f.video_id AND c.t = f.t AND c.x = gx.x AND c.y = gy.y)"""


def q(*ctes: str, select: str) -> str:
    return "WITH " + ",".join(c.strip() for c in ctes) + "\n" + select
