"""DuckDB SQL for the registered queries: the definitions over the raw tables, by theta joins and without grid, leaves or bounds."""

from __future__ import annotations

VENUE = """
visit AS (
  SELECT event_id, user_id, epoch_us(ts) AS t0, CAST(json_extract_string(props, '$.k') AS INTEGER) % 25 AS v, unnest(range(4 + event_id % 31)) AS i FROM events
), venue AS (
  SELECT user_id * 100000 + (CAST(floor(t0 / 86400000000e0) AS BIGINT) - 19723) AS track_id, event_id * 64 + i AS fix_id, t0 + i * 30000000 AS t_us,
         500e0 * (v % 5) + ((user_id * 37) % 41 - 20) + 3 * (i % 5) AS x, 500e0 * (v // 5) + ((user_id * 53) % 41 - 20) + 2 * (i % 7) AS y, user_id AS owner_id
  FROM visit
)"""
VENUE_USER = VENUE + ", fixu AS (SELECT owner_id AS track_id, fix_id, t_us, x, y, owner_id FROM venue)"
LABELLED = """
sampled AS (
  SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY track_id ORDER BY t_us, fix_id) - 1 AS r FROM venue WHERE owner_id % 10 = 0) WHERE r % 3 = 1
), labelled AS (
  SELECT -track_id - 1 AS track_id, fix_id, t_us, x + ((fix_id * 7) % 11 - 5) * (1 + 6 * (track_id % 4)) AS x, y + ((fix_id * 3) % 11 - 5) * (1 + 6 * (track_id % 4)) AS y, track_id AS true_track_id FROM sampled
)"""
SHIPMENT = """
shipment AS (
  SELECT l_suppkey AS track_id, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS fix_id,
         epoch_us(l_shipdate) AS t_us, 100e0 * (l_partkey % 40) AS x, 100e0 * ((l_partkey // 40) % 40) AS y FROM lineitem
)"""
VECTOR = "vector AS (SELECT CAST(label AS BIGINT) AS track_id, vec_id AS fix_id, vec_id * 1000000 AS t_us, CAST(embedding[1] AS DOUBLE) * 100 AS x, CAST(embedding[2] AS DOUBLE) * 100 AS y FROM embeddings)"


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(p.strip() for p in parts) + "\n"


def segmented(src: str, name: str = "seg", gap_m: float = 200, gap_us: int = 1_800_000_000, period: str = "false", where: str = "true") -> str:
    """Fixes of src with seg_no by the hop rule."""
    far = "false" if gap_m is None else f"sqrt((x - px) * (x - px) + (y - py) * (y - py)) > {gap_m!r}e0 OR t_us - pt > {gap_us}".replace(".0e0", "e0").replace("ee", "e")
    return f"""{name} AS (
  SELECT *, CAST(sum(CASE WHEN {far} OR {period} THEN 1 ELSE 0 END) OVER (PARTITION BY track_id ORDER BY t_us, fix_id ROWS UNBOUNDED PRECEDING) AS INTEGER) AS seg_no
  FROM (SELECT *, lag(x) OVER w AS px, lag(y) OVER w AS py, lag(t_us) OVER w AS pt FROM {src} WHERE {where} WINDOW w AS (PARTITION BY track_id ORDER BY t_us, fix_id))
)"""


def rolled(src: str, name: str) -> str:
    return f"{name} AS (SELECT track_id, seg_no, count(*) AS n, min(t_us) AS st_us, max(t_us) AS et_us, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM {src} GROUP BY track_id, seg_no)"


DAY_BREAK = "floor(t_us / 86400000000e0) <> floor(pt / 86400000000e0)"


def weights(src: str = "caseseg", name: str = "weight") -> str:
    return f"""{name} AS (
  SELECT case_id, seg_no, n, span / sum(span) OVER (PARTITION BY case_id) AS weight
  FROM (SELECT track_id AS case_id, seg_no, count(*) AS n, (max(t_us) - min(t_us)) / 1e6 + 1 AS span FROM {src} GROUP BY track_id, seg_no)
)"""


def near(store: str, theta_d: float = 50, theta_t: float = 120, cases: str = "caseseg", name: str = "near") -> str:
    """Fix pairs in reach."""
    return f"""{name} AS (
  SELECT c.track_id AS case_id, c.seg_no, c.fix_id AS case_fix, f.track_id, sqrt((c.x - f.x) * (c.x - f.x) + (c.y - f.y) * (c.y - f.y)) AS d, abs(c.t_us - f.t_us) / 1e6 AS dt
  FROM {cases} c JOIN {store} f ON f.t_us BETWEEN c.t_us - {round(theta_t * 1e6)} AND c.t_us + {round(theta_t * 1e6)} AND f.track_id <> c.track_id
  WHERE sqrt((c.x - f.x) * (c.x - f.x) + (c.y - f.y) * (c.y - f.y)) <= {float(theta_d)!r}
)"""


def rate_parts(lam: float = 0.5, theta_d: float = 50, theta_t: float = 120, src: str = "near", suffix: str = "") -> str:
    """cor, srate and rate from fix pairs."""
    return f"""cor{suffix} AS (
  SELECT case_id, seg_no, case_fix, track_id, max({lam}e0 * exp(-(d / {theta_d}e0)) + (1e0 - {lam}e0) * exp(-(dt / {theta_t}e0))) AS cor FROM {src} WHERE d <= {theta_d}e0 AND dt <= {theta_t}e0 GROUP BY ALL
), srate{suffix} AS (
  SELECT case_id, seg_no, track_id, weight, sum(cor) / any_value(n) AS seg_rate FROM cor{suffix} JOIN weight USING (case_id, seg_no) GROUP BY case_id, seg_no, track_id, weight
), rate{suffix} AS (SELECT case_id, track_id, sum(weight * seg_rate) AS rate FROM srate{suffix} GROUP BY case_id, track_id)""".replace(".0e0", "e0")


F1 = [VENUE, segmented("venue", "caseseg", where="owner_id % 10 = 0"), weights(), near("venue"), rate_parts()]
F2 = [VENUE, LABELLED, segmented("labelled", "caseseg"), weights(), near("venue"), rate_parts()]
FU = [VENUE_USER, segmented("fixu", "caseseg", where="owner_id % 10 = 0"), weights(), near("fixu"), rate_parts()]
STORE = [segmented("venue", "storefix", period=DAY_BREAK), rolled("storefix", "store")]
CASEBOX = rolled("caseseg", "casebox")
CASES = [VENUE, segmented("venue", "caseseg", where="owner_id % 10 = 0"), CASEBOX]

O: dict[str, str] = {}

for _k, _parts, _src in (("fix_venue", [VENUE], "venue"), ("fix_labelled", [VENUE, LABELLED], "labelled"), ("fix_shipment", [SHIPMENT], "shipment"), ("fix_vector", [VECTOR], "vector")):
    O[_k] = with_(*_parts) + f"SELECT track_id, count(*) AS n, CAST(sum(fix_id) AS BIGINT) AS ids, min(t_us) AS first_us, max(t_us) AS last_us, round(sum(x), 6) AS sx, round(sum(y), 6) AS sy FROM {_src} GROUP BY track_id"

O["clean_outliers"] = with_(VENUE) + """
SELECT track_id, count(*) AS n, CAST(sum(fix_id) AS BIGINT) AS ids FROM (
  SELECT *, sqrt(power(x - lag(x) OVER w, 2) + power(y - lag(y) OVER w, 2)) AS d1, (t_us - lag(t_us) OVER w) / 1e6 AS t1,
         sqrt(power(x - lead(x) OVER w, 2) + power(y - lead(y) OVER w, 2)) AS d2, (lead(t_us) OVER w - t_us) / 1e6 AS t2
  FROM venue WINDOW w AS (PARTITION BY track_id ORDER BY t_us, fix_id)
) WHERE NOT (coalesce(d1 > 50e0 * t1, false) AND coalesce(d2 > 50e0 * t2, false)) GROUP BY track_id"""
O["clean_sequential"] = with_(VENUE_USER, """
ranked AS (SELECT *, row_number() OVER (PARTITION BY track_id ORDER BY t_us, fix_id) AS r FROM fixu),
walk AS (
  SELECT track_id, r, fix_id, t_us AS kt, x AS kx, y AS ky, true AS kept FROM ranked WHERE r = 1
  UNION ALL
  SELECT track_id, r, fix_id, CASE WHEN ok THEN t_us ELSE kt END, CASE WHEN ok THEN x ELSE kx END, CASE WHEN ok THEN y ELSE ky END, ok
  FROM (SELECT n.*, w.kt, w.kx, w.ky, sqrt((n.x - w.kx) * (n.x - w.kx) + (n.y - w.ky) * (n.y - w.ky)) <= 50e0 * (n.t_us - w.kt) / 1e6 AS ok FROM walk w JOIN ranked n ON n.track_id = w.track_id AND n.r = w.r + 1)
)""") + "SELECT track_id, count(*) AS n, CAST(sum(fix_id) AS BIGINT) AS ids FROM walk WHERE kept GROUP BY track_id"
O["clean_repeats"] = with_(VENUE_USER) + "SELECT track_id, count(*) AS n, CAST(sum(fix_id) AS BIGINT) AS ids FROM (SELECT track_id, t_us, min(fix_id) AS fix_id FROM fixu GROUP BY track_id, t_us) GROUP BY track_id"

_SEGCOLS = "SELECT track_id, seg_no, CAST(n AS INTEGER) AS n, st_us, et_us, x0, x1, y0, y1 FROM box"
O["segment_gap"] = with_(VENUE, segmented("venue")) + "SELECT track_id, seg_no, count(*) AS n, min(fix_id) AS low, max(fix_id) AS high FROM seg GROUP BY track_id, seg_no"
O["segment_rollup"] = with_(VENUE, segmented("venue"), rolled("seg", "box")) + _SEGCOLS
O["segment_period"] = with_(VENUE, segmented("venue", period=DAY_BREAK), rolled("seg", "box")) + _SEGCOLS
O["segment_max_fixes"] = with_(VENUE, segmented("venue"), """
cut AS (SELECT *, (row_number() OVER (PARTITION BY track_id, seg_no ORDER BY t_us, fix_id) - 1) // 8 AS part FROM seg),
renum AS (SELECT track_id, fix_id, t_us, x, y, CAST(dense_rank() OVER (PARTITION BY track_id ORDER BY seg_no, part) - 1 AS INTEGER) AS seg_no FROM cut)""", rolled("renum", "box")) + _SEGCOLS
O["segment_anchor"] = with_(VENUE, """
ranked AS (SELECT *, row_number() OVER (PARTITION BY track_id ORDER BY t_us, fix_id) AS r FROM venue),
walk AS (
  SELECT track_id, r, fix_id, t_us, x, y, 0 AS seg_no, t_us AS since, x AS ax, y AS ay FROM ranked WHERE r = 1
  UNION ALL
  SELECT n.track_id, n.r, n.fix_id, n.t_us, n.x, n.y, CASE WHEN f THEN seg_no + 1 ELSE seg_no END, CASE WHEN f THEN n.t_us ELSE since END, CASE WHEN f THEN n.x ELSE ax END, CASE WHEN f THEN n.y ELSE ay END
  FROM (SELECT w.seg_no, w.since, w.ax, w.ay, n.*, n.t_us - w.since > 1800000000 OR sqrt((n.x - w.ax) * (n.x - w.ax) + (n.y - w.ay) * (n.y - w.ay)) > 200e0 AS f FROM walk w JOIN ranked n ON n.track_id = w.track_id AND n.r = w.r + 1) n
)""", rolled("walk", "box")) + _SEGCOLS
O["segment_diameter"] = with_(VENUE, """
ranked AS (SELECT *, row_number() OVER (PARTITION BY track_id ORDER BY t_us, fix_id) AS r FROM venue),
walk AS (
  SELECT track_id, r, fix_id, t_us, x, y, 0 AS seg_no, t_us AS since, [x] AS xs, [y] AS ys FROM ranked WHERE r = 1
  UNION ALL
  SELECT n.track_id, n.r, n.fix_id, n.t_us, n.x, n.y, CASE WHEN f THEN seg_no + 1 ELSE seg_no END, CASE WHEN f THEN n.t_us ELSE since END, CASE WHEN f THEN [n.x] ELSE list_append(xs, n.x) END, CASE WHEN f THEN [n.y] ELSE list_append(ys, n.y) END
  FROM (SELECT w.seg_no, w.since, w.xs, w.ys, n.*, n.t_us - w.since > 1800000000 OR list_max(list_transform(list_zip(w.xs, w.ys), lambda p: sqrt((n.x - p[1]) * (n.x - p[1]) + (n.y - p[2]) * (n.y - p[2])))) > 10e0 AS f FROM walk w JOIN ranked n ON n.track_id = w.track_id AND n.r = w.r + 1) n
)""", rolled("walk", "box")) + _SEGCOLS
O["extend_box"] = with_(*CASES) + "SELECT track_id, seg_no, CAST(n AS INTEGER) AS n, st_us - 120000000 AS st_us, et_us + 120000000 AS et_us, x0 - 50 AS x0, x1 + 50 AS x1, y0 - 50 AS y0, y1 + 50 AS y1 FROM casebox"

O["fn_pair_correlation"] = "SELECT event_id, round(CASE WHEN event_id % 61 <= 50 AND event_id % 151 <= 120 THEN 0.5e0 * exp(-((event_id % 61) / 50e0)) + 0.5e0 * exp(-((event_id % 151) / 120e0)) ELSE 0 END, 6) AS cor FROM events"
O["fn_haversine"] = with_(VECTOR) + """
SELECT fix_id, round(2 * 6371008.8e0 * asin(sqrt(least(1e0, power(sin((radians(y / 10 - 0.02e0) - radians(y / 10)) / 2), 2) + cos(radians(y / 10)) * cos(radians(y / 10 - 0.02e0)) * power(sin(radians(x / 10 + 0.01e0 - x / 10) / 2), 2)))), 4) AS metres FROM vector"""
O["fn_json_venue"] = "SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) % 25 AS venue, count(*) AS n FROM events GROUP BY 1"
O["fn_period_bin"] = """
SELECT DISTINCT epoch_us(l_shipdate) AS t_us, CAST(date_diff('hour', TIMESTAMP '1970-01-01', l_shipdate) // 5 AS BIGINT) AS hour5, date_diff('day', TIMESTAMP '1970-01-01', l_shipdate) AS day,
       CAST(date_diff('day', TIMESTAMP '1970-01-01', l_shipdate) // 7 AS BIGINT) AS week, date_diff('month', TIMESTAMP '1970-01-01', l_shipdate) AS month,
       CAST(date_diff('month', TIMESTAMP '1970-01-01', l_shipdate) // 3 AS BIGINT) AS quarter, date_diff('year', TIMESTAMP '1970-01-01', l_shipdate) AS year FROM lineitem"""
_XZ = """
norm AS (SELECT track_id, seg_no, st_us, (x0 + 1024) / 4096e0 AS ax, (y0 + 1024) / 4096e0 AS ay, (x1 + 1024) / 4096e0 AS bx, (y1 + 1024) / 4096e0 AS tall FROM box),
descent AS (
  SELECT *, 0 AS level, 0e0 AS cx, 0e0 AS cy, CAST(0 AS BIGINT) AS code FROM norm
  UNION ALL
  SELECT track_id, seg_no, st_us, ax, ay, bx, tall, level + 1, nx, ny, code + 1 + (CASE WHEN nx > cx THEN 1 ELSE 0 END + CASE WHEN ny > cy THEN 2 ELSE 0 END) * CAST((power(4, 12 - level) - 1) / 3 AS BIGINT)
  FROM (SELECT *, CASE WHEN ax >= cx + power(0.5e0, level + 1) THEN cx + power(0.5e0, level + 1) ELSE cx END AS nx, CASE WHEN ay >= cy + power(0.5e0, level + 1) THEN cy + power(0.5e0, level + 1) ELSE cy END AS ny FROM descent WHERE level < 12)
  WHERE bx <= nx + 2 * power(0.5e0, level + 1) AND tall <= ny + 2 * power(0.5e0, level + 1)
)"""
O["fn_xz_code"] = with_(VENUE, segmented("venue", period=DAY_BREAK), rolled("seg", "box"), _XZ) + "SELECT track_id, seg_no, max(code) AS xz, CAST(floor(any_value(st_us) / 86400000000e0) AS BIGINT) * 1099511627776 + max(code) AS key FROM descent GROUP BY track_id, seg_no"
O["fn_leaf_cell"] = with_(VENUE) + """
SELECT CAST(list_sum([(((ix >> b) & 1) + 2 * ((iy >> b) & 1)) * CAST(power(4, b) AS BIGINT) FOR b IN range(5)]) AS BIGINT) AS cell, count(*) AS n
FROM (SELECT CAST(floor((x + 1024) / 128) AS BIGINT) AS ix, CAST(floor((y + 1024) / 128) AS BIGINT) AS iy FROM venue) GROUP BY 1"""

O["fix_correlation"] = with_(*F1) + "SELECT case_id, seg_no, case_fix, track_id, round(cor, 6) AS cor FROM cor"
O["segment_weight"] = with_(VENUE, segmented("venue", "caseseg", where="owner_id % 10 = 0"), weights()) + "SELECT case_id, seg_no, CAST(n AS INTEGER) AS n, round(weight, 6) AS weight FROM weight"
O["segment_rate"] = with_(*F1) + "SELECT case_id, seg_no, track_id, round(weight, 6) AS weight, round(seg_rate, 6) AS seg_rate FROM srate"
O["track_rate"] = with_(*F1) + "SELECT case_id, track_id, round(rate, 6) AS rate FROM rate"
O["track_rate_user"] = with_(*FU) + "SELECT case_id, track_id, round(rate, 6) AS rate FROM rate"
O["op_brute_force"] = with_(VECTOR, segmented("vector", "caseseg"), weights(), near("vector", 50, 30), rate_parts(0.5, 50, 30)) + "SELECT case_id, track_id, round(rate, 6) AS rate FROM rate"

_MEET = "c.x0 - 50 <= s.x1 AND s.x0 <= c.x1 + 50 AND c.y0 - 50 <= s.y1 AND s.y0 <= c.y1 + 50 AND c.st_us - 120000000 <= s.et_us AND s.st_us <= c.et_us + 120000000"
_GAP = "sqrt(power(greatest(0e0, c.x0 - s.x1, s.x0 - c.x1), 2) + power(greatest(0e0, c.y0 - s.y1, s.y0 - c.y1), 2)) <= 50e0"
FOUND = f"found AS (SELECT c.track_id AS case_id, c.seg_no, s.track_id, s.seg_no AS store_seg FROM casebox c JOIN store s ON {_MEET} AND c.track_id <> s.track_id WHERE {_GAP})"
BOXES = [*CASES, *STORE, FOUND]
O["st_reject"] = O["leaf_candidates"] = with_(*BOXES) + "SELECT * FROM found"
O["box_bound"] = with_(*BOXES, """
best AS (
  SELECT case_id, seg_no, track_id, fix_id, max(0.5e0 * exp(-(d / 50e0)) + 0.5e0 * exp(-(dt / 120e0))) AS cor FROM (
    SELECT f.case_id, f.seg_no, f.track_id, c.fix_id, sqrt(power(greatest(0e0, s.x0 - c.x, c.x - s.x1), 2) + power(greatest(0e0, s.y0 - c.y, c.y - s.y1), 2)) AS d, greatest(0, s.st_us - c.t_us, c.t_us - s.et_us) / 1e6 AS dt
    FROM found f JOIN caseseg c ON c.track_id = f.case_id AND c.seg_no = f.seg_no JOIN store s ON s.track_id = f.track_id AND s.seg_no = f.store_seg)
  WHERE d <= 50e0 AND dt <= 120e0 GROUP BY ALL
)""") + "SELECT case_id, b.seg_no, b.track_id, round(sum(cor) / any_value(n), 6) AS bound FROM best b JOIN casebox c ON c.track_id = b.case_id AND c.seg_no = b.seg_no GROUP BY case_id, b.seg_no, b.track_id"
O["cover_bound"] = with_(*F1) + """
SELECT case_id, track_id, round(exp(-1e0) * sum(weight * k / n), 6) AS low, round(sum(weight * k / n), 6) AS high
FROM (SELECT case_id, seg_no, track_id, count(DISTINCT case_fix) AS k FROM near GROUP BY ALL) JOIN weight USING (case_id, seg_no) GROUP BY case_id, track_id"""

AUDIT = """
marked AS (
  SELECT *, weight * seg_rate AS irp, sum(weight) OVER (PARTITION BY case_id, track_id) AS met,
         coalesce(sum(weight * seg_rate) OVER (PARTITION BY case_id, track_id ORDER BY seg_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS done,
         coalesce(sum(weight) OVER (PARTITION BY case_id, track_id ORDER BY seg_no ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) AS rest
  FROM srate
)"""


O["prune_running_weight"] = with_(*F1, AUDIT.replace("ORDER BY seg_no", "ORDER BY weight DESC, seg_no")) + """
SELECT DISTINCT case_id, track_id FROM marked WHERE irp - (0.5 - done - rest) < -1e-9"""


def audit(theta: float) -> str:
    return f"""SELECT case_id, track_id, sum(irp) AS rate, sum(weight) < {theta} - 1e-9 AS by_weight, bool_or(irp - ({theta} - 1 + weight) < -1e-9) AS by_single,
  bool_or(irp - ({theta} - (met - weight)) < -1e-9) AS by_hit, bool_or(irp - ({theta} - done - rest) < -1e-9) AS by_running FROM marked GROUP BY case_id, track_id"""


O["prune_weight"] = with_(*F1) + "SELECT case_id, track_id, round(sum(weight), 6) AS met FROM srate GROUP BY case_id, track_id HAVING sum(weight) >= 0.5e0 - 1e-9"
for _k in ("single", "hit", "running"):
    O[f"prune_{_k}"] = with_(*F1, AUDIT) + f"SELECT case_id, track_id FROM ({audit(0.5)}) WHERE by_{_k}"
O["prune_mandatory"] = with_(*F1) + """
SELECT case_id, track_id FROM (SELECT DISTINCT case_id, track_id FROM srate) p
WHERE NOT EXISTS (SELECT 1 FROM weight w WHERE w.case_id = p.case_id AND w.weight > 0.5e0 + 1e-9 AND NOT EXISTS (SELECT 1 FROM srate s WHERE s.case_id = p.case_id AND s.track_id = p.track_id AND s.seg_no = w.seg_no))"""
O["prune_audit"] = with_(*F1, AUDIT) + f"SELECT * REPLACE (round(rate, 6) AS rate) FROM ({audit(0.5)})"
O["measure_pruned"] = with_(*F1, AUDIT) + f"SELECT count(*) AS pairs, count_if(by_weight) AS weight, count_if(by_single) AS single, count_if(by_hit) AS hit, count_if(by_running) AS running, count_if(rate > 0.5) AS answers FROM ({audit(0.5)})"
O["measure_pruned_thetas"] = with_(*F1, AUDIT) + " UNION ALL ".join(f"SELECT {t}e0 AS theta, count_if(NOT by_weight) AS kept_weight, count_if(NOT by_running) AS kept_running, count_if(rate > {t}) AS answers FROM ({audit(t)})" for t in (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7))

_ANSWER = "SELECT case_id, track_id, round(rate, 6) AS rate FROM rate WHERE rate > {}"
for _k in ("query_pruned", "query_unpruned", "query_waves", "query_fold", "join_pruned", "join_unpruned", "join_no_leaves", "join_limited_leaves"):
    O[_k] = with_(*F1) + _ANSWER.format(0.5)
O["query_low_theta"] = with_(*F1) + _ANSWER.format(0.05)
MOST = "(SELECT track_id FROM {} WHERE owner_id % 10 = 0 GROUP BY track_id ORDER BY count(*) DESC, track_id LIMIT 1)"
O["query_one_track"] = O["query_one_track_unpruned"] = with_(*F1) + _ANSWER.format(0.02) + f" AND case_id = {MOST.format('venue')}"
O["query_one_user"] = with_(*FU) + _ANSWER.format(0.005) + f" AND case_id = {MOST.format('fixu')}"
GEO = VENUE + ", geo AS (SELECT track_id, fix_id, t_us, 116e0 + x / 80000e0 AS x, 39e0 + y / 111000e0 AS y, owner_id FROM venue)"


def sphere(ax: str, ay: str, bx: str, by: str) -> str:
    """Great-circle metres."""
    return (
        f"(2 * 6371008.8e0 * asin(sqrt(least(1e0, power(sin((radians({by}) - radians({ay})) / 2), 2)"
        f" + cos(radians({ay})) * cos(radians({by})) * power(sin(radians({bx} - {ax}) / 2), 2)))))"
    )


_GEO_SEGMENTS = f"""caseseg AS (
  SELECT *, CAST(sum(CASE WHEN {sphere("px", "py", "x", "y")} > 200e0 OR t_us - pt > 1800000000 THEN 1 ELSE 0 END) OVER (PARTITION BY track_id ORDER BY t_us, fix_id ROWS UNBOUNDED PRECEDING) AS INTEGER) AS seg_no
  FROM (SELECT *, lag(x) OVER w AS px, lag(y) OVER w AS py, lag(t_us) OVER w AS pt FROM geo WHERE owner_id % 10 = 0 WINDOW w AS (PARTITION BY track_id ORDER BY t_us, fix_id))
)"""
_GEO_NEAR = f"""near AS (
  SELECT * FROM (
    SELECT c.track_id AS case_id, c.seg_no, c.fix_id AS case_fix, f.track_id, {sphere("c.x", "c.y", "f.x", "f.y")} AS d, abs(c.t_us - f.t_us) / 1e6 AS dt
    FROM caseseg c JOIN geo f ON f.t_us BETWEEN c.t_us - 120000000 AND c.t_us + 120000000 AND f.track_id <> c.track_id
  ) WHERE d <= 50e0
)"""
FG = [GEO, _GEO_SEGMENTS, weights(), _GEO_NEAR, rate_parts()]
O["query_degrees"] = O["query_degrees_fold"] = O["join_degrees"] = with_(*FG) + _ANSWER.format(0.3)
O["query_degrees_one_track"] = with_(*FG) + _ANSWER.format(0.02) + f" AND case_id = {MOST.format('geo')}"
O["incubation_window"] = with_(VENUE_USER, "recent AS (SELECT * FROM (SELECT *, max(t_us) OVER (PARTITION BY track_id) AS last_us FROM fixu WHERE owner_id % 10 = 0) WHERE t_us > last_us - 1209600000000)", segmented("recent", "caseseg"), weights(), near("fixu"), rate_parts()) + _ANSWER.format(0.02)
O["topk_contacts"] = with_(*F1) + "SELECT * FROM (SELECT case_id, track_id, round(rate, 6) AS rate, CAST(row_number() OVER (PARTITION BY case_id ORDER BY round(rate, 9) DESC, track_id) AS INTEGER) AS place FROM rate) WHERE place <= 2"
O["default_run"] = with_(*F2) + _ANSWER.format(0.5)


def cell(r: int) -> str:
    size = 4096 // 2**r
    return f"celled AS (SELECT track_id AS case_id, seg_no, st_us, et_us, x0, x1, y0, y1, CAST(coalesce(list_sum([(((ix >> b) & 1) + 2 * ((iy >> b) & 1)) * CAST(power(4, b) AS BIGINT) FOR b IN range({r})]), 0) AS BIGINT) AS cell FROM (SELECT *, CAST(floor((x0 + 1024) / {size}) AS BIGINT) AS ix, CAST(floor((y0 + 1024) / {size}) AS BIGINT) AS iy FROM casebox))"


ISLANDS = """
island AS (
  SELECT *, CAST(sum(opens) OVER (PARTITION BY cell ORDER BY st_us, et_us, case_id, seg_no ROWS UNBOUNDED PRECEDING) - 1 AS INTEGER) AS island FROM (
    SELECT *, CASE WHEN coalesce(st_us > max(et_us) OVER (PARTITION BY cell ORDER BY st_us, et_us, case_id, seg_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), true) THEN 1 ELSE 0 END AS opens FROM celled)
)"""
LEAVES = "leaf AS (SELECT cell, island, count(*) AS n, min(st_us) AS st_us, max(et_us) AS et_us, min(x0) AS x0, max(x1) AS x1, min(y0) AS y0, max(y1) AS y1 FROM island GROUP BY cell, island)"
O["leaf_islands"] = with_(*CASES, cell(2), ISLANDS) + "SELECT case_id, seg_no, cell, island FROM island"
O["leaf_build"] = with_(*CASES, cell(2), ISLANDS, LEAVES) + "SELECT * FROM leaf"
O["leaf_limited"] = with_(*CASES, cell(1), """
ranked AS (SELECT *, row_number() OVER (PARTITION BY cell ORDER BY st_us, et_us, case_id, seg_no) AS r FROM celled),
walk AS (
  SELECT case_id, seg_no, cell, r, 0 AS island, st_us AS low, et_us AS high, 1 AS held FROM ranked WHERE r = 1
  UNION ALL
  SELECT n.case_id, n.seg_no, n.cell, n.r, CASE WHEN f THEN island + 1 ELSE island END, CASE WHEN f THEN st_us ELSE low END, CASE WHEN f THEN et_us ELSE greatest(high, et_us) END, CASE WHEN f THEN 1 ELSE held + 1 END
  FROM (SELECT w.island, w.low, w.high, w.held, n.*, n.st_us > w.high OR greatest(w.high, n.et_us) - w.low > 1800000000 OR w.held = 3 AS f FROM walk w JOIN ranked n ON n.cell = w.cell AND n.r = w.r + 1) n
)""") + "SELECT case_id, seg_no, cell, island FROM walk"
O["leaf_tree"] = with_(*CASES, cell(1), ISLANDS, LEAVES, """
lv1 AS (SELECT cell, CAST(r // 8 AS BIGINT) AS node, count(*) AS children, min(st_us) AS st_us, max(et_us) AS et_us, min(x0) AS x0, max(x1) AS x1, min(y0) AS y0, max(y1) AS y1 FROM (SELECT *, row_number() OVER (PARTITION BY cell ORDER BY st_us, island) - 1 AS r FROM leaf) GROUP BY 1, 2),
lv2 AS (SELECT cell, CAST(node // 8 AS BIGINT) AS node, count(*) AS children, min(st_us) AS st_us, max(et_us) AS et_us, min(x0) AS x0, max(x1) AS x1, min(y0) AS y0, max(y1) AS y1 FROM lv1 GROUP BY 1, 2)""") + "SELECT *, 1 AS level FROM lv1 UNION ALL SELECT *, 2 FROM lv2"
_FETCH = "SELECT c.cell, c.island, s.track_id, s.seg_no FROM {} c JOIN store s ON " + _MEET


def fetched(r: int | None, name: str) -> str:
    if r is None:
        return f"SELECT count(*) AS accesses, 1 AS largest, (SELECT count(*) FROM casebox c JOIN store s ON {_MEET}) AS fetched, (SELECT count(*) FROM (SELECT DISTINCT s.track_id, s.seg_no FROM casebox c JOIN store s ON {_MEET})) AS distinct_fetched, -1 AS resolution FROM casebox"
    return f"SELECT (SELECT count(*) FROM leaf{name}) AS accesses, (SELECT max(n) FROM leaf{name}) AS largest, count(*) AS fetched, count(DISTINCT (track_id, seg_no)) AS distinct_fetched, {r} AS resolution FROM ({_FETCH.format(f'leaf{name}')})"


def _leaves(r: int) -> str:
    parts = ", ".join([cell(r), ISLANDS, LEAVES])
    for w in ("celled", "island AS", "FROM island", "leaf AS"):
        parts = parts.replace(w, w.replace("celled", f"celled{r}").replace("island AS", f"island{r} AS").replace("FROM island", f"FROM island{r}").replace("leaf AS", f"leaf{r} AS"))
    return parts.replace(f"AS INTEGER) AS island{r} FROM", "AS INTEGER) AS island FROM").replace(f"- 1 AS INTEGER) AS island{r}", "- 1 AS INTEGER) AS island")


O["sweep_resolution"] = with_(*CASES, *STORE, *(_leaves(r) for r in range(5))) + " UNION ALL ".join([*(fetched(r, str(r)) for r in range(5)), fetched(None, "")])
O["measure_redundancy"] = with_(*CASES, *STORE, cell(1), ISLANDS, LEAVES) + f"SELECT count(*) AS fetched, count(DISTINCT (track_id, seg_no)) AS distinct_fetched FROM ({_FETCH.format('leaf')})"
O["measure_accesses"] = with_(*CASES, cell(1), ISLANDS, LEAVES) + "SELECT (SELECT count(*) FROM casebox) AS segments, (SELECT count(*) FROM leaf) AS leaves"
O["measure_candidates"] = with_(*BOXES, weights()) + """
SELECT (SELECT count(*) FROM found) AS segment_pairs, (SELECT count(*) FROM (SELECT DISTINCT case_id, track_id FROM found)) AS pairs,
       (SELECT count(*) FROM (SELECT case_id, track_id FROM (SELECT DISTINCT case_id, seg_no, track_id FROM found) JOIN weight USING (case_id, seg_no) GROUP BY 1, 2 HAVING sum(weight) >= 0.5e0 - 1e-9)) AS kept"""
_PART = "SELECT {p} AS pruned, (SELECT count(*) FROM {f}) AS segment_pairs, count(*) AS segments, CAST(sum(n) AS BIGINT) AS fixes FROM store WHERE (track_id, seg_no) IN (SELECT (track_id, store_seg) FROM {f})"
_LAG = "greatest(0, c.st_us - s.et_us, s.st_us - c.et_us) / 1e6"
O["measure_saving"] = with_(*BOXES, weights(), f"""
need AS (SELECT case_id, count_if(weight > 0.5e0 + 1e-9) AS need FROM weight GROUP BY case_id),
tops AS (
  SELECT f.case_id, f.seg_no, f.track_id, max(0.5e0 * exp(-({_GAP.replace(" <= 50e0", "")} / 50e0)) + 0.5e0 * exp(-({_LAG} / 120e0))) AS most
  FROM found f JOIN casebox c ON c.track_id = f.case_id AND c.seg_no = f.seg_no JOIN store s ON s.track_id = f.track_id AND s.seg_no = f.store_seg GROUP BY f.case_id, f.seg_no, f.track_id
), kept AS (
  SELECT case_id, track_id FROM tops JOIN weight USING (case_id, seg_no) JOIN need USING (case_id)
  GROUP BY case_id, track_id, need HAVING sum(weight * most) >= 0.5e0 - 1e-9 AND count_if(weight > 0.5e0 + 1e-9) >= need
), less AS (SELECT * FROM found WHERE (case_id, track_id) IN (SELECT (case_id, track_id) FROM kept))""") + _PART.format(p="false", f="found") + " UNION ALL " + _PART.format(p="true", f="less")
O["measure_evaluations"] = with_(VENUE, segmented("venue", "caseseg", where="owner_id % 10 = 0"), near("venue")) + "SELECT count(*) AS evaluations, count(DISTINCT (case_id, case_fix)) AS fixes FROM near"
O["measure_leaf_load"] = with_(*CASES, cell(1), ISLANDS, LEAVES) + "SELECT n, count(*) AS leaves, max((et_us - st_us) / 1e6) AS longest_s FROM leaf GROUP BY n"

_DAY0 = 19723 * 86_400_000_000
O["store_range_query"] = with_(VENUE, *STORE) + f"SELECT track_id, seg_no, CAST(floor(st_us / 86400000000e0) AS BIGINT) AS bin, CAST(n AS INTEGER) AS n FROM store WHERE x0 <= 1100 AND x1 >= 400 AND y0 <= 1600 AND y1 >= 900 AND st_us <= {_DAY0 + 5 * 86_400_000_000} AND et_us >= {_DAY0 + 2 * 86_400_000_000}"
O["store_window_query"] = with_(*CASES, *STORE) + f"SELECT concat_ws(':', c.track_id, c.seg_no) AS window_id, s.track_id, s.seg_no FROM casebox c JOIN store s ON {_MEET}"
O["store_by_track"] = with_(VENUE, *STORE) + "SELECT track_id, seg_no, CAST(n AS INTEGER) AS n FROM store WHERE track_id // 100000 % 10 = 0"
O["op_scan_ranges"] = with_(VENUE, """
win AS (
  SELECT track_id AS window_id, (min(x) + 1024) / 4096e0 AS x0, (min(y) + 1024) / 4096e0 AS y0, (max(x) + 1024) / 4096e0 AS x1, (max(y) + 1024) / 4096e0 AS y1
  FROM venue WHERE owner_id % 10 = 0 AND track_id % 100000 = owner_id % 30 GROUP BY track_id
), visit4 AS (
  SELECT window_id, x0, y0, x1, y1, 0 AS level, 0 AS ix, 0 AS iy, CAST(0 AS BIGINT) AS code, true AS descend, CAST(0 AS BIGINT) AS low, CAST(0 AS BIGINT) AS high FROM win
  UNION ALL
  SELECT window_id, x0, y0, x1, y1, level, ix, iy, code, part AND level < 4, code, CASE WHEN part THEN code ELSE code + size - 1 END FROM (
    SELECT *, NOT (lx >= x0 AND hx <= x1 AND ly >= y0 AND hy <= y1) AS part FROM (
      SELECT *, CASE WHEN ix = 0 THEN -1e9 ELSE ix * side END AS lx, CASE WHEN iy = 0 THEN -1e9 ELSE iy * side END AS ly,
             CASE WHEN ix >= cells - 2 THEN 1e9 ELSE (ix + 2) * side END AS hx, CASE WHEN iy >= cells - 2 THEN 1e9 ELSE (iy + 2) * side END AS hy FROM (
        SELECT v.window_id, v.x0, v.y0, v.x1, v.y1, v.level + 1 AS level, 2 * v.ix + q % 2 AS ix, 2 * v.iy + q // 2 AS iy, v.code + 1 + q * CAST((power(4, 4 - v.level) - 1) / 3 AS BIGINT) AS code,
               CAST((power(4, 4 - v.level) - 1) / 3 AS BIGINT) AS size, power(0.5e0, v.level + 1) AS side, CAST(power(2, v.level + 1) AS INTEGER) AS cells
        FROM visit4 v, range(4) r(q) WHERE v.descend)))
    WHERE lx <= x1 AND hx >= x0 AND ly <= y1 AND hy >= y0
), codes AS (SELECT DISTINCT window_id, unnest(range(low, high + 1)) AS code FROM visit4)""") + """
SELECT window_id, min(code) AS low, max(code) AS high FROM (SELECT window_id, code, code - row_number() OVER (PARTITION BY window_id ORDER BY code) AS g FROM codes) GROUP BY window_id, g"""

O["dataset_stats"] = with_(VENUE, segmented("venue")) + "SELECT CAST(sum(n) AS BIGINT) AS fixes, count(*) AS tracks, CAST(sum(s) AS BIGINT) AS segments, round(avg(n), 6) AS fixes_per_track FROM (SELECT track_id, count(*) AS n, count(DISTINCT seg_no) AS s FROM seg GROUP BY track_id)"


def quality(answers: str, labels: str = "labels", by: str = "") -> str:
    return f"SELECT {by}(SELECT count(*) FROM {labels}) AS queries, count(*) AS pairs, round(count_if(a.track_id = l.true_track_id) / count(*), 6) AS accuracy, round(count(DISTINCT case_id) / (SELECT count(*) FROM {labels}), 6) AS recall FROM {answers} a JOIN {labels} l USING (case_id)"


LABELS = "truth AS (SELECT DISTINCT track_id AS case_id, true_track_id FROM labelled)"


def grid(points: list[tuple[str, float, float, float, float]]) -> str:
    """Quality at explicit points (column list, lam, theta_d, theta_t, theta): one set of rate CTEs each over the widest fix pairs."""
    d, t = max(p[2] for p in points), max(p[3] for p in points)
    parts = [VENUE, LABELLED, LABELS, segmented("labelled", "caseseg"), weights(), near("venue", d, t), *(rate_parts(p[1], p[2], p[3], suffix=str(i)) for i, p in enumerate(points))]
    return with_(*parts) + " UNION ALL ".join(quality(f"(SELECT * FROM rate{i} WHERE rate > {p[4]}e0)", "truth", p[0]) for i, p in enumerate(points))


def sweep(param: str, values: list[float]) -> str:
    base = {"lam": 0.5, "theta_d": 50.0, "theta_t": 120.0, "theta": 0.5}
    points = [(f"'{param}' AS param, {v}e0 AS value, ", *(v if k == param else base[k] for k in ("lam", "theta_d", "theta_t", "theta"))) for v in values]
    return grid(points)


O["sweep_lambda"] = sweep("lam", [0.0, 0.25, 0.5, 0.75, 1.0])
_THETAS = [0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9]
_THETA_SWEEP = " UNION ALL ".join(quality(f"(SELECT * FROM rate WHERE rate > {v}e0)", "truth", f"'theta' AS param, {v}e0 AS value, ") for v in _THETAS)
O["sweep_theta"] = with_(*F2, LABELS) + f"SELECT * FROM ({_THETA_SWEEP}) WHERE pairs > 0"
O["sweep_distance"] = sweep("theta_d", [20.0, 50.0, 100.0, 150.0])
O["sweep_time"] = sweep("theta_t", [60.0, 120.0, 300.0, 600.0])
O["sweep_query_size"] = with_(*F2, LABELS) + " UNION ALL ".join(quality("(SELECT * FROM rate WHERE rate > 0.5e0)", f"(SELECT * FROM truth WHERE (abs(case_id) % 10) * 10 < {v})", f"'query_size' AS param, {v}e0 AS value, ") for v in (20, 40, 60, 80, 100))
O["sweep_pivot"] = with_(*F2, LABELS, f"runs AS ({_THETA_SWEEP})") + "SELECT m AS measure, max(CASE WHEN value = 0.1 THEN v END) AS t1, max(CASE WHEN value = 0.5 THEN v END) AS t5, max(CASE WHEN value = 0.9 THEN v END) AS t9 FROM (SELECT value, 'accuracy' AS m, accuracy AS v FROM runs UNION ALL SELECT value, 'recall', recall FROM runs) GROUP BY m"
O["calibrate_grid"] = grid([(f"{a}e0 AS lam, {d}e0 AS theta_d, 120e0 AS theta_t, {t}e0 AS theta, round(count(DISTINCT CASE WHEN a.track_id = l.true_track_id THEN case_id END) / (SELECT count(*) FROM truth), 6) AS true_hit, ", a, d, 120.0, t) for a in (0.25, 0.75) for d in (50.0, 100.0) for t in (0.3, 0.5)])
O["calibrate_choice"] = f"SELECT * FROM ({O['calibrate_grid']}) ORDER BY accuracy * recall DESC, lam, theta_d, theta_t, theta LIMIT 1"
_Q = with_(*F2, LABELS, "ans AS (SELECT * FROM rate JOIN truth USING (case_id) WHERE rate > 0.5e0)")
O["measure_accuracy"] = _Q + "SELECT count(*) AS pairs, round(count_if(track_id = true_track_id) / count(*), 6) AS accuracy FROM ans"
O["measure_recall"] = _Q + "SELECT (SELECT count(*) FROM truth) AS queries, round(count(DISTINCT case_id) / (SELECT count(*) FROM truth), 6) AS recall FROM ans"
O["measure_true_hit"] = _Q + "SELECT (SELECT count(*) FROM truth) AS queries, round(count(DISTINCT case_id) FILTER (track_id = true_track_id) / (SELECT count(*) FROM truth), 6) AS true_hit FROM ans"
O["sweep_data_size"] = with_(VENUE, segmented("venue", "caseseg", where="owner_id % 10 = 0"), weights(), "big AS (SELECT track_id + j * CAST(1000000000 AS BIGINT) AS track_id, t_us + j * 20000000 AS t_us, x + 7 * j AS x, y - 5 * j AS y, j FROM venue, range(5) r(j))", near("big"), rate_parts()) + " UNION ALL ".join(
    f"SELECT (SELECT count(*) FROM big WHERE j < {c}) AS fixes, (SELECT count(DISTINCT track_id) FROM big WHERE j < {c}) AS tracks, count(*) AS pairs, count(DISTINCT case_id) AS answered, {c} AS copies FROM rate WHERE rate > 0.5e0 AND track_id < CAST({c} AS BIGINT) * 1000000000" for c in range(1, 6)
)

_UNITS = {"day": "date_diff('day', TIMESTAMP '1970-01-01', make_timestamp({}))", "week": "date_diff('day', TIMESTAMP '1970-01-01', make_timestamp({})) // 7", "month": "date_diff('month', TIMESTAMP '1970-01-01', make_timestamp({}))", "year": "date_diff('year', TIMESTAMP '1970-01-01', make_timestamp({}))"}
_U = []
for _k, _e in _UNITS.items():
    _U.append(segmented("shipment", f"seg_{_k}", 1e9, 864_000_000_000, f"{_e.format('t_us')} <> {_e.format('pt')}").replace("1000000000.0e0", "1e9"))
    _U.append(rolled(f"seg_{_k}", f"box_{_k}"))
O["period_units"] = with_(SHIPMENT, *_U) + " UNION ALL ".join(f"SELECT CAST({e.format('st_us')} AS BIGINT) AS bin, count(*) AS segments, CAST(sum(n) AS BIGINT) AS fixes, '{k}' AS unit FROM box_{k} GROUP BY 1" for k, e in _UNITS.items())
O["shipment_rates"] = with_(SHIPMENT, segmented("shipment", "caseseg", 1e9, 864_000_000_000, where="track_id % 10 = 0"), weights(), near("shipment", 300, 86400), rate_parts(0.5, 300, 86400)) + "SELECT case_id, track_id, round(rate, 6) AS rate FROM rate"

OWNED = "owned AS (SELECT case_id, track_id, rate, c_custkey, case_id % 100000 AS day, n_name, r_name FROM rate JOIN customer ON c_custkey = track_id // 100000 JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)"
O["risk_rollup"] = with_(*F1, OWNED) + "SELECT r_name, n_name, count(*) AS pairs, count(DISTINCT c_custkey) AS people, round(max(rate), 6) AS top FROM owned GROUP BY ROLLUP (r_name, n_name)"
O["risk_cube"] = with_(*F1, OWNED) + "SELECT r_name, day, count(*) AS pairs FROM owned GROUP BY CUBE (r_name, day)"
O["risk_grouping_sets"] = with_(*F1, OWNED) + "SELECT r_name, day, count(*) AS pairs, count(DISTINCT c_custkey) AS people FROM owned GROUP BY GROUPING SETS ((r_name), (day), ())"

O["op_filter_window"] = with_(VENUE) + "SELECT track_id, fix_id, x FROM venue WHERE x BETWEEN 400 AND 1100 AND owner_id IN (1, 2, 3, 5, 8)"
_CONTACT = "SELECT case_id, track_id, count(*) AS n FROM near GROUP BY case_id, track_id"
O["op_broadcast_contact"] = O["op_merge_contact"] = O["op_salted_contact"] = with_(VENUE, segmented("venue", "caseseg", where="owner_id % 10 = 0"), near("venue")) + _CONTACT
O["op_interval_join"] = "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.event_id < b.event_id AND a.event_type = b.event_type AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 120000000"
O["op_asof_fix"] = """
SELECT p.event_id, (SELECT max_by(c.event_id, (epoch_us(c.ts), c.event_id)) FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND (c.ts < p.ts OR c.ts = p.ts AND c.event_id < p.event_id)) AS click_id
FROM events p WHERE p.event_type = 'purchase'"""
O["op_keep_pairs"] = with_(*F1) + "SELECT case_id, track_id, seg_no FROM (SELECT *, sum(weight) OVER (PARTITION BY case_id, track_id) AS met FROM srate) WHERE met >= 0.5e0 - 1e-9"
O["op_drop_pairs"] = with_(*F1) + "SELECT case_id, track_id, seg_no FROM (SELECT *, min(weight * seg_rate - (0.5e0 - 1 + weight)) OVER (PARTITION BY case_id, track_id) AS slack FROM srate) WHERE slack >= -1e-9"
O["op_union"] = with_(*F1) + "SELECT case_id, track_id FROM rate WHERE rate > 0.1 OR rate < 0.4"
O["op_intersect"] = with_(*F1) + "SELECT case_id, track_id FROM rate WHERE rate > 0.1 AND rate < 0.4"
O["op_except"] = with_(*F1) + "SELECT case_id, track_id FROM rate WHERE rate > 0.1 AND NOT rate < 0.4"
O["op_exists_contact"] = with_(*F1) + "SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT track_id // 100000 FROM rate WHERE rate > (SELECT avg(rate) FROM rate))"
O["op_top_pairs"] = with_(*F1) + "SELECT case_id, track_id, round(rate, 6) AS rate FROM rate ORDER BY round(rate, 6) DESC, case_id, track_id LIMIT 20"
O["downsample"] = with_(VENUE) + "SELECT -track_id - 1 AS track_id, track_id AS true_track_id, count(*) AS n, CAST(sum(fix_id) AS BIGINT) AS ids FROM (SELECT *, row_number() OVER (PARTITION BY track_id ORDER BY t_us, fix_id) - 1 AS r FROM venue) WHERE r % 5 = 0 GROUP BY track_id"
O["scale_copies"] = with_(VENUE) + "SELECT track_id + j * 1000000000 AS track_id, count(*) AS n, CAST(sum(fix_id) AS BIGINT) AS ids, min(t_us) + j * 20000000 AS first_us, max(t_us) + j * 20000000 AS last_us, round(sum(x + 7 * j), 6) AS sx, round(sum(y - 5 * j), 6) AS sy FROM venue, range(3) r(j) GROUP BY track_id, j"
O["query_fraction"] = with_(VENUE, LABELLED) + "SELECT track_id, count(*) AS n FROM labelled WHERE (abs(track_id) % 10) * 10 < 40 GROUP BY track_id"

LISTS = VECTOR + """, lists AS (
  SELECT track_id, list(x ORDER BY t_us, fix_id) AS xs, list(y ORDER BY t_us, fix_id) AS ys FROM vector GROUP BY track_id
), duo AS (SELECT a.track_id AS a, b.track_id AS b, a.xs AS ax, a.ys AS ay, b.xs AS bx, b.ys AS by_, len(a.xs) AS n, len(b.xs) AS m FROM lists a JOIN lists b ON a.track_id < b.track_id)"""
O["cmp_euclid"] = with_(LISTS) + "SELECT a, b, round(list_sum([sqrt(power(ax[i] - bx[i], 2) + power(ay[i] - by_[i], 2)) FOR i IN range(1, least(n, m) + 1)]) / least(n, m), 6) AS value FROM duo"


def diagonals(combine: str) -> str:
    """Two anti-diagonals of the cost matrix carried along; combine has {best} and {cost}."""
    best = "least(coalesce(d1[i + 1], 1e18), coalesce(d1[i], 1e18), coalesce(d2[i], 1e18))"
    cost = "sqrt(power(ax[i] - bx[k - i + 1], 2) + power(ay[i] - by_[k - i + 1], 2))"
    cell_ = combine.format(best=f"(CASE WHEN k = 1 THEN 0e0 ELSE {best} END)", cost=cost)
    return f"""walk AS (
  SELECT *, 0 AS k, CAST([] AS DOUBLE[]) AS d1, CAST([] AS DOUBLE[]) AS d2 FROM duo
  UNION ALL
  SELECT a, b, ax, ay, bx, by_, n, m, k, list_prepend(1e18, list_transform(range(1, n + 1), lambda i: CASE WHEN k - i + 1 BETWEEN 1 AND m THEN {cell_} ELSE 1e18 END)), d1
  FROM (SELECT a, b, ax, ay, bx, by_, n, m, k + 1 AS k, d1, d2 FROM walk WHERE k < n + m - 1)
)"""


O["cmp_dtw"] = with_(LISTS, diagonals("{best} + {cost}")) + "SELECT a, b, round(d1[n + 1], 6) AS value FROM walk WHERE k = n + m - 1"
O["cmp_frechet"] = with_(LISTS, diagonals("greatest({best}, {cost})")) + "SELECT a, b, round(d1[n + 1], 6) AS value FROM walk WHERE k = n + m - 1"


def mix(cases: str, fixes: str) -> str:
    return f"""
SELECT a, b, round(0.5e0 * sum(exp(-(d / 50e0))) / any_value(n) + 0.5e0 * sum(exp(-(dt / 120e0))) / any_value(n), 6) AS value FROM (
  SELECT c.track_id AS a, f.track_id AS b, c.fix_id, min(sqrt(power(c.x - f.x, 2) + power(c.y - f.y, 2))) AS d, min(abs(c.t_us - f.t_us) / 1e6) AS dt
  FROM {cases} c JOIN {fixes} f ON f.t_us BETWEEN c.t_us - 120000000 AND c.t_us + 120000000 AND f.track_id <> c.track_id GROUP BY ALL
) JOIN (SELECT track_id AS a, count(*) AS n FROM {cases} GROUP BY 1) USING (a) GROUP BY a, b"""


O["cmp_linear_mix"] = with_(VENUE, "own AS (SELECT * FROM venue WHERE owner_id % 10 = 0)") + mix("own", "venue")
_SPAN = f"t_us BETWEEN {_DAY0 + 3 * 86_400_000_000} AND {_DAY0 + 6 * 86_400_000_000}"
O["cmp_windowed"] = with_(VENUE, f"part AS (SELECT * FROM venue WHERE {_SPAN})", "own AS (SELECT * FROM part WHERE owner_id % 10 = 0)") + mix("own", "part")
O["cmp_unsegmented"] = with_(VENUE, "caseseg AS (SELECT *, 0 AS seg_no FROM venue WHERE owner_id % 10 = 0)", weights(), near("venue"), rate_parts()) + "SELECT case_id, track_id, round(rate, 6) AS rate FROM rate"
COMPANIONS = """
snap AS (SELECT track_id, k, arg_max(x, (t_us, fix_id)) AS x, arg_max(y, (t_us, fix_id)) AS y FROM (SELECT *, t_us // 60000000 AS k FROM venue) GROUP BY track_id, k),
close AS (SELECT a.track_id AS a, b.track_id AS b, a.k FROM snap a JOIN snap b ON a.k = b.k AND a.track_id < b.track_id WHERE sqrt(power(a.x - b.x, 2) + power(a.y - b.y, 2)) <= 50e0),
runs AS (SELECT a, b, min(k) AS first_slot, count(*) AS slots FROM (SELECT *, k - row_number() OVER (PARTITION BY a, b ORDER BY k) AS g FROM close) GROUP BY a, b, g HAVING count(*) >= 2)"""
O["companions"] = with_(VENUE, COMPANIONS) + "SELECT * FROM runs"
O["companion_groups"] = with_(VENUE, COMPANIONS, "link AS (SELECT a, b FROM runs UNION SELECT b, a FROM runs), reach AS (SELECT a AS track_id, a AS seen FROM link UNION SELECT r.track_id, l.b FROM reach r JOIN link l ON r.seen = l.a)") + "SELECT track_id, min(seen) AS group_id FROM reach GROUP BY track_id"

O["udf_xz_code"] = with_(VENUE, segmented("venue", period=DAY_BREAK, where="owner_id % 10 = 0"), rolled("seg", "box"), _XZ) + "SELECT track_id, seg_no, max(code) AS xz FROM descent GROUP BY track_id, seg_no"
O["fn_row_key"] = with_(VENUE, segmented("venue", period=DAY_BREAK, where="owner_id % 10 = 0"), rolled("seg", "box"), _XZ) + """
SELECT track_id, seg_no, bin, xz, seg_id, printf('%016X', bin * 1099511627776 + xz) || '-' || seg_id AS code_part, true AS shard_in_range
FROM (SELECT track_id, seg_no, CAST(floor(any_value(st_us) / 86400000000e0) AS BIGINT) AS bin, max(code) AS xz, track_id || ':' || seg_no AS seg_id FROM descent GROUP BY track_id, seg_no)"""
O["udf_track_rate"] = O["track_rate"]
O["sql_functions"] = with_(VENUE) + """
SELECT CAST(floor(t_us / 86400000000e0) AS BIGINT) AS bin, CAST(list_sum([(((ix >> b) & 1) + 2 * ((iy >> b) & 1)) * CAST(power(4, b) AS BIGINT) FOR b IN range(3)]) AS BIGINT) AS cell, count(*) AS n, round(sum(0.5e0 * exp(-((x - floor(x)) / 50e0)) + 0.5e0), 6) AS cor
FROM (SELECT *, CAST(floor((x + 1024) / 512) AS BIGINT) AS ix, CAST(floor((y + 1024) / 512) AS BIGINT) AS iy FROM venue) GROUP BY 1, 2"""
_W = "SELECT track_id, (t_us // 3600000000) * 3600000000 AS start_us, count(*) AS fixes FROM venue GROUP BY 1, 2"
O["stream_windows"] = with_(VENUE) + _W
O["stream_sliding"] = with_(VENUE) + "SELECT track_id, start_us, count(*) AS fixes FROM (SELECT track_id, (t_us // 1800000000 - j) * 1800000000 AS start_us FROM venue, range(2) r(j)) GROUP BY 1, 2"
O["stream_sessions"] = with_(VENUE) + """
SELECT track_id, min(t_us) AS start_us, count(*) AS fixes FROM (
  SELECT *, sum(CASE WHEN t_us - pt >= 1800000000 THEN 1 ELSE 0 END) OVER (PARTITION BY track_id ORDER BY t_us, fix_id ROWS UNBOUNDED PRECEDING) AS s
  FROM (SELECT *, lag(t_us) OVER (PARTITION BY track_id ORDER BY t_us, fix_id) AS pt FROM venue)) GROUP BY track_id, s"""
O["stream_distinct"] = with_(VENUE) + "SELECT DISTINCT track_id, fix_id FROM venue"
O["stream_contacts"] = O["op_merge_contact"]
O["stream_live_contacts"] = O["op_broadcast_contact"]
O["stream_segments"] = O["segment_gap"]
O["stream_late"] = with_(VENUE, """
dealt AS (
  SELECT v.track_id, v.t_us, least(2, CAST(ceil(day(e.ts) / 11e0) AS INTEGER) - 1 + CASE WHEN e.event_id // 20 % 7 = 0 THEN 1 ELSE 0 END) AS part FROM venue v JOIN events e ON e.event_id = v.fix_id // 64
), newest AS (SELECT p.part, max(d.t_us) AS t_us FROM (SELECT DISTINCT part FROM dealt) p JOIN dealt d ON d.part < p.part GROUP BY p.part)""") + """
SELECT track_id, count_if(NOT late) AS fixes, count_if(late) AS late FROM (
  SELECT d.track_id, coalesce(d.t_us < n.t_us - 3600000000, false) AS late FROM dealt d LEFT JOIN newest n USING (part)
) GROUP BY track_id"""


def oracle_sql() -> dict[str, str]:
    return dict(O)
