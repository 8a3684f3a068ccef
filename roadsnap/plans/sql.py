"""The derived networks as DuckDB CTEs, from which the oracles are put together."""

SIDE = "g AS (SELECT CAST(ceil(sqrt(count(*))) AS BIGINT) AS w, count(*) AS parts, max(p_partkey) AS top FROM part)"
GRID_V = SIDE + ",\nv AS (SELECT p_partkey AS vid, p_partkey % w AS x, p_partkey // w AS y, p_size FROM part, g)"
GRID_E = (
    GRID_V
    + """,
e AS (SELECT a.vid * 4 + d.dir AS eid, a.vid AS src, b.vid AS dst, CAST(50 + 5 * (a.p_size + b.p_size) AS BIGINT) AS length_m
  FROM v a CROSS JOIN (VALUES (0, 1, 0), (1, -1, 0), (2, 0, 1), (3, 0, -1)) d(dir, dx, dy) JOIN v b ON b.x = a.x + d.dx AND b.y = a.y + d.dy)"""
)


def snaps(period: str) -> str:
    return f"s AS (SELECT CAST(row_number() OVER (ORDER BY t) - 1 AS INTEGER) AS snap, t AS t_from FROM (SELECT DISTINCT CAST(date_trunc('{period}', l_shipdate) AS DATE) AS t FROM lineitem))"


def grid(period: str = "quarter") -> str:
    """v, e, s, wt(snap, eid, w_ms)."""
    return (
        GRID_E
        + ",\n"
        + snaps(period)
        + f""",
ld AS (SELECT snap, l_partkey AS dst, CAST(sum(l_quantity) AS BIGINT) AS load FROM lineitem JOIN s ON CAST(date_trunc('{period}', l_shipdate) AS DATE) = t_from GROUP BY ALL),
tot AS (SELECT CAST(sum(load) AS BIGINT) AS tt, (SELECT count(*) FROM s) AS n FROM ld),
wt AS (SELECT snap, eid, CAST((length_m * 1000 * (tt + coalesce(load, 0) * n * parts)) // (15 * tt) AS BIGINT) AS w_ms FROM e CROSS JOIN s CROSS JOIN tot CROSS JOIN g LEFT JOIN ld USING (snap, dst))"""
    )


ROUTES = """
ends AS (SELECT l_orderkey AS pid, first(l_partkey ORDER BY l_linenumber, l_suppkey, l_partkey, l_shipdate, l_extendedprice, l_quantity) AS a,
    last(l_partkey ORDER BY l_linenumber, l_suppkey, l_partkey, l_shipdate, l_extendedprice, l_quantity) AS b FROM lineitem GROUP BY 1),
leg AS (SELECT pid, a % w AS xa, a // w AS ya, b % w AS xb, b // w AS yb, w, (a // w) * w + b % w > top AS df, abs(b % w - a % w) AS nh, abs(b // w - a // w) AS nv FROM ends, g WHERE a <> b),
stp AS (SELECT *, unnest(range(nh + nv)) AS seq FROM leg),
pe AS (SELECT pid, CAST(seq AS INTEGER) AS seq, CAST(CASE WHEN (CASE WHEN df THEN seq >= nv ELSE seq < nh END)
    THEN ((CASE WHEN df THEN yb ELSE ya END) * w + xa + sign(xb - xa) * (CASE WHEN df THEN seq - nv ELSE seq END)) * 4 + (CASE WHEN xb > xa THEN 0 ELSE 1 END)
    ELSE ((ya + sign(yb - ya) * (CASE WHEN df THEN seq ELSE seq - nh END)) * w + (CASE WHEN df THEN xa ELSE xb END)) * 4 + (CASE WHEN yb > ya THEN 2 ELSE 3 END) END AS BIGINT) AS eid FROM stp)"""

PLANTED = (
    GRID_E
    + """,
day AS (SELECT CAST(i AS INTEGER) AS snap, CASE WHEN i < 72 OR i >= 264 THEN 'night' WHEN i < 84 THEN 'ramp-a' WHEN i < 114 THEN 'morning' WHEN i < 192 THEN 'midday'
    WHEN i < 204 THEN 'ramp-b' WHEN i < 240 THEN 'evening' ELSE 'wind-down' END AS regime FROM range(288) r(i)),
ns AS (SELECT CAST(l_orderkey % 288 AS INTEGER) AS snap, l_partkey AS dst, CAST(4 * sum(l_quantity) AS BIGINT) AS noise FROM lineitem GROUP BY ALL),
cel AS (SELECT snap, eid, length_m, coalesce(noise, 0) AS noise, CASE regime WHEN 'morning' THEN 2000 WHEN 'ramp-a' THEN 1000 WHEN 'midday' THEN 500 WHEN 'ramp-b' THEN 1000 WHEN 'evening' THEN 2000 WHEN 'wind-down' THEN 700 ELSE 0 END AS amp,
    greatest(0, 1000 - (4000 * (CASE regime WHEN 'midday' THEN abs(x - w // 2) + abs(y - w // 2) WHEN 'morning' THEN abs(x - w // 4) + abs(y - w // 4) WHEN 'ramp-a' THEN abs(x - w // 4) + abs(y - w // 4)
      ELSE abs(x - 3 * w // 4) + abs(y - 3 * w // 4) END)) // w) AS influence
  FROM e JOIN v ON v.vid = e.dst CROSS JOIN g CROSS JOIN day LEFT JOIN ns USING (snap, dst)),
wt AS (SELECT snap, eid, CAST(((length_m * 1000) // 15) * (1000 + (amp * influence) // 1000 + noise) // 1000 AS BIGINT) AS w_ms FROM cel)"""
)

TRADE_MOVES = """
ln AS (SELECT l.*, s_nationkey AS nat, lag(s_nationkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_suppkey, l_partkey, l_shipdate, l_extendedprice, l_quantity) AS prev
  FROM lineitem l JOIN supplier ON l_suppkey = s_suppkey),
mv AS (SELECT l_orderkey AS pid, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_suppkey, l_partkey, l_shipdate, l_extendedprice, l_quantity) - 1 AS INTEGER) AS seq,
    CAST(prev * 25 + nat AS BIGINT) AS eid, CAST(date_trunc('quarter', l_shipdate) AS DATE) AS t_from, CAST(round(l_extendedprice * 100) AS BIGINT) AS cents, CAST(l_quantity AS BIGINT) AS qty
  FROM ln WHERE prev IS NOT NULL AND prev <> nat)"""
TRADE = (
    TRADE_MOVES
    + ",\n"
    + snaps("quarter")
    + """,
e AS (SELECT eid, eid // 25 AS src, eid % 25 AS dst, 100 * (abs(eid // 25 // 5 - eid % 25 // 5) + abs(eid // 25 % 5 - eid % 25 % 5)) AS length_m FROM (SELECT DISTINCT eid FROM mv)),
cl AS (SELECT snap, eid, CAST(sum(cents) AS BIGINT) AS cents, CAST(sum(qty) AS BIGINT) AS qty FROM mv JOIN s USING (t_from) GROUP BY ALL),
wt AS (SELECT snap, e.eid, CAST(coalesce(10 * cl.cents // cl.qty, o.w, (SELECT 10 * CAST(sum(cents) AS BIGINT) // CAST(sum(qty) AS BIGINT) FROM cl)) AS BIGINT) AS w_ms
  FROM e CROSS JOIN s LEFT JOIN cl USING (snap, eid) LEFT JOIN (SELECT eid, 10 * CAST(sum(cents) AS BIGINT) // CAST(sum(qty) AS BIGINT) AS w FROM cl GROUP BY 1) o ON o.eid = e.eid),
pe AS (SELECT pid, seq, eid FROM mv)"""
)
EVENT_MOVES = """
pl AS (SELECT *, CAST(json_extract_string(props, '$.k') AS BIGINT) // 10 AS bucket FROM events),
lg AS (SELECT *, lag(bucket) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev FROM pl),
em AS (SELECT user_id AS pid, prev * 10 + bucket AS eid, ts, event_id, CAST(round(value * 1000) AS BIGINT) AS obs_ms FROM lg WHERE prev IS NOT NULL AND prev <> bucket)"""
COSTS = "c AS (SELECT snap, pid, CAST(sum(w_ms) AS BIGINT) AS d_ms FROM pe JOIN wt USING (eid) GROUP BY ALL)"
ERRORS = """er AS (SELECT a.snap AS typ, b.snap AS act, round(CAST(sum(abs(a.d_ms - b.d_ms) * 1000000000 // b.d_ms) AS BIGINT) / count(*) / 1000000000, 9) AS err
  FROM c a JOIN c b USING (pid) GROUP BY ALL)"""
TRADE_ERRORS = f"{TRADE},\n{COSTS},\n{ERRORS}"


def reach(r_ms: int, origins: str = "SELECT vid FROM v", weights: str = "wt", name: str = "rc") -> str:
    """A recursive CTE; the query must begin WITH RECURSIVE."""
    return f"""ar_{name} AS (SELECT snap, src, dst, w_ms FROM {weights} JOIN e USING (eid)),
{name}(snap, origin, reached, dist_ms) USING KEY (snap, origin, reached) AS (
  SELECT DISTINCT w.snap, o.vid, o.vid, CAST(0 AS BIGINT) FROM {weights} w, ({origins}) o
  UNION
  SELECT * FROM (SELECT x.snap, x.origin, ar.dst, min(x.dist_ms + ar.w_ms) AS dn FROM {name} x JOIN ar_{name} ar ON ar.snap = x.snap AND ar.src = x.reached WHERE x.dist_ms + ar.w_ms <= {r_ms} GROUP BY ALL) n
  WHERE NOT EXISTS (SELECT 1 FROM recurring.{name} k WHERE k.snap = n.snap AND k.origin = n.origin AND k.reached = n.dst AND k.dist_ms <= n.dn))"""


BLOCKS = """sz AS (SELECT snap, origin AS vid, count(*) AS size FROM rc GROUP BY ALL),
bl AS (SELECT snap, vid, (max(size) OVER (PARTITION BY vid) * 1000000 // size) / 1000000 AS b FROM sz)"""
FLUCT = """fl AS (SELECT vid, round(sqrt(CAST(n * q - s * s AS DOUBLE)) / CAST(s AS DOUBLE), 6) AS f FROM (
  SELECT vid, CAST(sum(m) AS HUGEINT) AS s, CAST(sum(m * m) AS HUGEINT) AS q, count(*) AS n FROM (SELECT vid, CAST(round(b * 1000000) AS HUGEINT) AS m FROM bl) GROUP BY 1))"""
