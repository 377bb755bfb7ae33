"""The catalogue's queries in DuckDB SQL, written independently of the operators."""

from __future__ import annotations

from .experiments import CLIENTS, FAILURES, JOINERS, RATIOS, WORKERS
from .metrics import BEAT_BYTES, BEAT_REPLY_BYTES, BEATS_AFTER, EDGE_BYTES, GROUP_BYTES, KEPT_MODEL_BYTES, MAP_BYTES, MODEL_BYTES, OP_BYTES, REQUEST_BYTES, SLOT_BYTES, TAG_BYTES
from .timeline import COSTS as C

ITEMS = """items AS (SELECT CAST(substr(source, 4) AS BIGINT) AS sid, doc_id AS item, sha256(text) AS tag FROM documents WHERE text IS NOT NULL),
edges AS (SELECT sid, tag, min(item) AS item FROM items GROUP BY sid, tag)"""
FIRST = "SELECT tag, sid, item FROM (SELECT *, row_number() OVER (PARTITION BY tag ORDER BY (sid * 7919 + 17) % 20000, item, sid) AS r FROM {0}) WHERE r = 1"
WON = f"{ITEMS},\nfirst AS ({FIRST.format('edges')})"
LINES = """line_items AS (SELECT CAST(substr(source, 4) AS BIGINT) AS sid, (doc_id << 20) + p - 1 AS item, trim(parts[p], ' ') AS content
  FROM (SELECT source, doc_id, parts, unnest(range(1, len(parts) + 1)) AS p FROM (SELECT source, doc_id, string_split(text, chr(10)) AS parts FROM documents WHERE text IS NOT NULL)) WHERE trim(parts[p], ' ') <> ''),
line_edges AS (SELECT sid, sha256(content) AS tag, min(item) AS item FROM line_items GROUP BY 1, 2)"""
TAKE = """SELECT tag, from_sid, to_sid, taken_at FROM (SELECT r.tag, r.from_sid, e.sid AS to_sid, {at} + 1 + (e.sid * 137 + 11) % 1000 AS taken_at,
  row_number() OVER (PARTITION BY r.tag ORDER BY (e.sid * 137 + 11) % 1000, e.sid) AS k FROM {rel} r JOIN edges e USING (tag) WHERE e.sid NOT IN ({off})) WHERE k = 1"""
COURSE = f"""{WON},
rel1 AS (SELECT tag, sid AS from_sid FROM first WHERE sid IN (0, 18)),
take1 AS ({TAKE.format(at=30000, rel='rel1', off='0, 18')}),
hold1 AS (SELECT f.tag, f.sid AS first_sid, CASE WHEN f.sid IN (0, 18) THEN t.to_sid ELSE f.sid END AS holder FROM first f LEFT JOIN take1 t USING (tag)),
rel2 AS (SELECT tag, CAST(13 AS BIGINT) AS from_sid FROM hold1 WHERE holder = 13 AND first_sid <> 13),
take2 AS ({TAKE.format(at=35000, rel='rel2', off='0, 13, 18')}),
hold2 AS (SELECT h.tag, h.first_sid, CASE WHEN r.tag IS NOT NULL THEN t.to_sid ELSE h.holder END AS holder FROM hold1 h LEFT JOIN rel2 r USING (tag) LEFT JOIN take2 t USING (tag)),
back AS (SELECT DISTINCT tag FROM edges WHERE sid = 0),
fin AS (SELECT h.tag, h.first_sid, h.holder AS mid, CASE WHEN h.holder IS NULL AND b.tag IS NOT NULL THEN 0 ELSE h.holder END AS holder FROM hold2 h LEFT JOIN back b USING (tag)),
safe AS (SELECT tag, sid FROM (SELECT tag, sid, row_number() OVER (PARTITION BY tag ORDER BY sha256(tag || ':' || sid)) AS k FROM edges WHERE sid NOT IN (0, 13, 18)) WHERE k = 1),
anyone AS (SELECT tag, min(sid) AS sid FROM edges WHERE sid <> 18 GROUP BY tag),
chosen AS (SELECT f.tag, f.holder AS last_holder, CASE WHEN f.holder IS NOT NULL AND f.holder NOT IN (0, 13, 18) THEN f.holder WHEN s.sid IS NOT NULL THEN s.sid WHEN f.holder IN (0, 13) THEN f.holder ELSE a.sid END AS sid
  FROM fin f LEFT JOIN safe s USING (tag) LEFT JOIN anyone a USING (tag)),
assigned AS (SELECT tag, sid, last_holder, CASE WHEN sid IS NULL THEN 'unassigned' WHEN sid = last_holder THEN 'kept' WHEN last_holder IS NULL THEN 'new' ELSE 'moved' END AS how FROM chosen)"""

POOL = """lines AS (SELECT DISTINCT sha256(trim(part, ' ')) AS tag FROM (SELECT unnest(string_split(text, chr(10))) AS part FROM documents WHERE text IS NOT NULL) WHERE trim(part, ' ') <> ''),
ranked AS (SELECT tag, row_number() OVER (ORDER BY tag) - 1 AS place FROM lines),
sz AS (SELECT CASE WHEN count(*) >= 10240 THEN 1024 WHEN count(*) >= 2560 THEN 256 ELSE 64 END AS n FROM lines)"""


SPREAD = """prs AS (SELECT a, b, row_number() OVER (ORDER BY a, b) - 1 AS i FROM (SELECT unnest(range(0, 10)) AS a), (SELECT unnest(range(0, 10)) AS b) WHERE a < b),
twice AS (SELECT grid, unnest([a, b]) AS sid, k AS place FROM (SELECT grid, unnest(range(0, shared)) AS k FROM shares) JOIN prs ON k % 45 = i)"""


def grid(points: str, spread: bool = False) -> str:
    """Workloads of points (grid, c, n, d), matched or spread over all pairs of ten clients, and their winners."""
    matched = "twice AS (SELECT grid, slot % c AS sid, slot // 2 AS place FROM (SELECT grid, c, unnest(range(0, 2 * shared)) AS slot FROM shares))"
    return f"""{POOL},
points AS ({points}),
shares AS (SELECT grid, c, n, d, c * CAST(round(n * d) AS BIGINT) // 2 AS shared FROM points),
{SPREAD if spread else matched},
members AS (SELECT grid, n, shared, unnest(range(0, c)) AS sid FROM shares),
needs AS (SELECT m.grid, m.sid, m.shared, m.n - count(t.place) AS need FROM members m LEFT JOIN twice t ON t.grid = m.grid AND t.sid = m.sid GROUP BY m.grid, m.sid, m.shared, m.n),
starts AS (SELECT grid, sid, need, shared + coalesce(sum(need) OVER (PARTITION BY grid ORDER BY sid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start FROM needs),
placed AS (SELECT grid, sid, place FROM twice UNION ALL SELECT grid, sid, unnest(range(CAST(start AS BIGINT), CAST(start + need AS BIGINT))) FROM starts WHERE need > 0),
gedges AS (SELECT grid, sid, place * 64 + sid AS item, tag FROM placed JOIN ranked USING (place)),
gfirst AS (SELECT grid, tag, sid FROM (SELECT *, row_number() OVER (PARTITION BY grid, tag ORDER BY (sid * 7919 + 17) % 20000, item, sid) AS r FROM gedges) WHERE r = 1)"""


CLIENT_ROWS = """clients AS (SELECT e.grid, e.sid, (e.sid * 7919 + 17) % 20000 AS ready, count(*) AS n, count(f.tag) AS n_run FROM gedges e LEFT JOIN gfirst f ON f.grid = e.grid AND f.tag = e.tag AND f.sid = e.sid GROUP BY 1, 2)"""
LEVELS = """groups AS (SELECT grid, l, sid >> CAST(l AS INTEGER) AS g, count(DISTINCT tag) AS size FROM (SELECT e.grid, e.sid, e.tag, unnest(range(0, 4)) AS l, p.c FROM gedges e JOIN points p USING (grid)) WHERE (1 << CAST(l AS INTEGER)) < c GROUP BY 1, 2, 3),
pairs AS (SELECT grid, l, g >> 1 AS pair, sum(size) AS size FROM groups GROUP BY 1, 2, 3),
levels AS (SELECT grid, l, max(size) AS size FROM pairs GROUP BY 1, 2)"""


SERVED = f"""line AS (SELECT *, ready + n * {C.tag} // 1000 AS asked, row_number() OVER (PARTITION BY grid ORDER BY ready + n * {C.tag} // 1000, sid) AS k FROM clients),
served AS (SELECT grid, CAST(0 AS BIGINT) AS k, [CAST(0 AS BIGINT), 0, 0, 0] AS free, CAST(NULL AS BIGINT) AS done FROM points
  UNION ALL SELECT l.grid, l.k, list_append(list_sort(s.free)[2:4], CAST(greatest(list_min(s.free), l.asked) + l.n * {C.index} // 1000 AS BIGINT)), CAST(greatest(list_min(s.free), l.asked) + l.n * {C.index} // 1000 AS BIGINT)
  FROM served s JOIN line l ON l.grid = s.grid AND l.k = s.k + 1),
ended AS (SELECT l.*, s.done, {C.start_ms} + l.n_run * {C.train} // 1000 AS train FROM line l JOIN served s ON s.grid = l.grid AND s.k = l.k)"""


def turns(name: str, rows: str, asked: str, work: str) -> str:
    """Rows with begin and fin on one server that takes them in order."""
    return f"""{name}_q AS (SELECT *, sum({work}) OVER (PARTITION BY grid ORDER BY {asked}, sid) AS upto FROM {rows}),
{name} AS (SELECT *, max({asked} - upto + {work}) OVER (PARTITION BY grid ORDER BY {asked}, sid) + upto AS fin, max({asked} - upto + {work}) OVER (PARTITION BY grid ORDER BY {asked}, sid) + upto - {work} AS begun FROM {name}_q)"""


def end_to_end(points: str) -> str:
    return f"""WITH RECURSIVE {grid(points)}, {CLIENT_ROWS}, {LEVELS}, {SERVED}, {turns('trained', 'ended', 'done', 'train')},
conc AS (SELECT grid, max(fin) + {C.aggregate_ms + C.broadcast_ms} - min(ready) AS e2e, max(done - ready) AS dedup FROM trained GROUP BY grid),
tree AS (SELECT grid, sum(size * {C.pair} // 1000) AS ms FROM levels GROUP BY grid),
ser AS (SELECT c.grid, max(ready) - min(ready) AS wait, max(n) * {C.tag} // 1000 + coalesce(max(t.ms), 0) AS dedup, sum({C.start_ms} + n_run * {C.train} // 1000) AS train FROM clients c LEFT JOIN tree t USING (grid) GROUP BY c.grid),
vol AS (SELECT grid, count(*) AS total, count(DISTINCT tag) AS distinct_records, count(DISTINCT sid) AS clients FROM gedges GROUP BY grid)
SELECT CAST(grid AS BIGINT) AS grid, clients, total, distinct_records, CAST(conc.e2e AS BIGINT) AS concurrent_ms, CAST(ser.wait + ser.dedup + ser.train + {C.aggregate_ms + C.broadcast_ms} AS BIGINT) AS serial_ms,
  CAST(conc.dedup AS BIGINT) AS concurrent_dedup_ms, CAST(ser.dedup AS BIGINT) AS serial_dedup_ms FROM vol JOIN conc USING (grid) JOIN ser USING (grid)"""


BY_CLIENTS = "SELECT CAST(c AS BIGINT) AS grid, CAST(c AS BIGINT) AS c, CAST(n AS BIGINT) AS n, 0.3 AS d FROM sz, (SELECT unnest([" + ", ".join(map(str, CLIENTS)) + "]) AS c)"
BY_RATIO = "SELECT CAST(p AS BIGINT) AS grid, CAST(10 AS BIGINT) AS c, CAST(n AS BIGINT) AS n, p / 100.0 AS d FROM sz, (SELECT unnest([" + ", ".join(str(round(d * 100)) for d in RATIOS) + "]) AS p)"
BY_SCALE = "SELECT CAST(n * q // 4 AS BIGINT) AS grid, CAST(10 AS BIGINT) AS c, CAST(n * q // 4 AS BIGINT) AS n, 0.3 AS d FROM sz, (SELECT unnest([1, 2, 4, 6]) AS q)"
TEN = "SELECT CAST(10 AS BIGINT) AS grid, CAST(10 AS BIGINT) AS c, CAST(n AS BIGINT) AS n, 0.3 AS d FROM sz"
BY_JOINERS = "SELECT CAST(j AS BIGINT) AS grid, CAST(10 + j AS BIGINT) AS c, CAST(n AS BIGINT) AS n, 0.3 AS d FROM sz, (SELECT unnest([" + ", ".join(map(str, JOINERS)) + "]) AS j)"
PER_RECORD = TAG_BYTES * 2 + REQUEST_BYTES + OP_BYTES + 2 * GROUP_BYTES


def ledger(points: str) -> str:
    return f"""WITH {grid(points)}, u AS (SELECT p.grid, p.c, p.n, e.sid, count(*) AS k, (e.sid * 7919 + 17) % 20000 AS ready FROM gedges e JOIN points p USING (grid) GROUP BY p.grid, p.c, p.n, e.sid),
t AS (SELECT grid, c, sum(k) AS k, (max(ready) * count(*) - sum(ready)) // 1000 + count(*) * {BEATS_AFTER} AS beats, CAST(2 ** ceil(log2(c * n)) AS BIGINT) AS slots FROM u GROUP BY grid, c, n),
b AS (SELECT grid, c, k * {PER_RECORD} + beats * {BEAT_BYTES + BEAT_REPLY_BYTES} AS comm, slots * {SLOT_BYTES} + k * {EDGE_BYTES + MAP_BYTES} AS store, c * {2 * MODEL_BYTES} AS model FROM t)
SELECT grid, CAST(comm AS BIGINT) AS comm_bytes, CAST(store AS BIGINT) AS storage_bytes, CAST(model AS BIGINT) AS model_bytes, round(comm * 100 / model, 6) AS comm_percent, round(store * 100 / (c * {KEPT_MODEL_BYTES}), 6) AS storage_percent FROM b"""


TREE = """WITH RECURSIVE {items}, n AS (SELECT CAST(ceil(log2(max(sid) + 1)) AS BIGINT) AS levels FROM edges),
lv AS (SELECT unnest(range(0, levels)) AS level FROM n),
groups AS (SELECT level, sid >> CAST(level AS INTEGER) AS g, tag FROM edges, lv GROUP BY 1, 2, 3),
drops AS (SELECT level, tag, (g >> 1) AS pair FROM groups GROUP BY 1, 2, 3 HAVING count(*) = 2)"""

EVENTS = "b AS (SELECT user_id AS sid, ts, event_id AS id FROM events)"
SESSIONS = f"{EVENTS},\ng AS (SELECT *, CASE WHEN ts - lag(ts) OVER w > INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM b WINDOW w AS (PARTITION BY sid ORDER BY ts, id)),\ns AS (SELECT *, sum(fresh) OVER (PARTITION BY sid ORDER BY ts, id ROWS UNBOUNDED PRECEDING) AS session FROM g)"

FNV = "list_reduce(list_transform(range(1, length(h) + 1), lambda i: CAST(ascii(substr(h, i, 1)) AS HUGEINT)), lambda a, x: (xor(a, x) * 1099511628211) % 18446744073709551616, CAST(14695981039346656037 AS HUGEINT))"
TOY = """WITH RECURSIVE d AS (SELECT doc_id, (CAST('0x' || substr(sha256(text), 1, 15) AS BIGINT) % 2147483576 + 2) AS root FROM documents WHERE text IS NOT NULL),
p AS (SELECT doc_id, CAST(1 AS BIGINT) AS acc, CAST(CAST(root AS HUGEINT) * root % 2147483579 AS BIGINT) AS base, CAST(123456789 AS BIGINT) AS e FROM d
  UNION ALL SELECT doc_id, CASE WHEN e % 2 = 1 THEN acc * base % 2147483579 ELSE acc END, base * base % 2147483579, e // 2 FROM p WHERE e > 0)
SELECT doc_id, acc AS tag FROM p WHERE e = 0"""

RATES = ", ".join(str(round(r * 100)) for r in FAILURES)
FAILED = f"""{grid(TEN, True)}, rates AS (SELECT unnest([{RATES}]) AS percent), fails AS (SELECT sid, row_number() OVER (ORDER BY sha256('fail:' || sid)) AS r FROM (SELECT DISTINCT sid FROM gedges)),
lost AS (SELECT percent, sid FROM rates, fails WHERE r * 10 <= percent), rel AS (SELECT percent, tag, sid AS from_sid FROM gfirst JOIN lost USING (sid)),
nobody AS (SELECT percent, tag FROM rel WHERE false),
offers AS (SELECT r.percent, r.tag, 1 + (e.sid * 137 + 11) % 1000 AS "at" FROM rel r JOIN gedges e USING (tag) LEFT JOIN lost l ON l.percent = r.percent AND l.sid = e.sid WHERE l.sid IS NULL),
took AS (SELECT percent, tag, min("at") AS "at" FROM offers GROUP BY 1, 2), rec AS (SELECT percent, count(*) AS n, max("at") AS last FROM took GROUP BY 1),
early AS (SELECT percent, max(o."at") AS last, count(*) AS n FROM offers o JOIN nobody USING (percent, tag) GROUP BY 1),
live AS (SELECT r.percent, e.sid, e.tag FROM rates r, gedges e LEFT JOIN lost l ON l.percent = r.percent AND l.sid = e.sid WHERE l.sid IS NULL),
gs AS (SELECT percent, l, sid >> CAST(l AS INTEGER) AS g, count(DISTINCT tag) AS size FROM live, (SELECT unnest(range(0, 4)) AS l) GROUP BY 1, 2, 3),
ps AS (SELECT percent, l, g >> 1 AS pair, sum(size) AS size FROM gs GROUP BY 1, 2, 3), ls AS (SELECT percent, l, max(size) AS size FROM ps GROUP BY 1, 2),
again AS (SELECT percent, sum(size * {C.pair} // 1000) + (SELECT n FROM sz) * {C.tag} // 1000 AS ms FROM ls GROUP BY 1),
failures AS (SELECT CAST(r.percent AS BIGINT) AS percent, (SELECT count(*) FROM rel x WHERE x.percent = r.percent) AS released, coalesce(rec.n, 0) AS recoverable, CAST(coalesce(early.last + early.n * {C.promote} // 1000, 0) AS BIGINT) AS concurrent_dedup_ms,
  CAST(again.ms AS BIGINT) AS serial_dedup_ms, CAST(coalesce(rec.last + rec.n * {C.promote} // 1000, 0) AS BIGINT) AS concurrent_training_ms, CAST(again.ms + {C.start_ms} AS BIGINT) AS serial_training_ms FROM rates r LEFT JOIN rec USING (percent) LEFT JOIN early USING (percent) JOIN again USING (percent))"""
JOINED = f"""{grid(BY_JOINERS)}, old AS (SELECT DISTINCT grid, tag FROM gedges WHERE sid < 10), fresh AS (SELECT e.* FROM gedges e LEFT JOIN old o ON o.grid = e.grid AND o.tag = e.tag WHERE e.sid >= 10 AND o.tag IS NULL),
fwon AS (SELECT grid, tag, sid FROM (SELECT *, row_number() OVER (PARTITION BY grid, tag ORDER BY (sid * 7919 + 17) % 20000, item, sid) AS r FROM fresh) WHERE r = 1),
clients AS (SELECT e.grid, e.sid, (e.sid * 7919 + 17) % 20000 AS ready, count(*) AS n, count(f.tag) AS n_run FROM gedges e LEFT JOIN fwon f ON f.grid = e.grid AND f.tag = e.tag AND f.sid = e.sid WHERE e.sid >= 10 GROUP BY 1, 2), {SERVED},
{turns('cbegun', 'ended', 'done', 'train')},
asking AS (SELECT *, (9 + k) * (2 * n * {C.check} // 1000) AS checks, {C.start_ms} + n_run * {C.train} // 1000 AS train FROM line), {turns('checked', 'asking', 'asked', 'checks')},
found AS (SELECT grid, sid, ready, train, fin AS done FROM checked), {turns('sbegun', 'found', 'done', 'train')},
joins AS (SELECT c.grid AS joiners, CAST(c.new_edges AS BIGINT) AS new_edges, CAST(c.won AS BIGINT) AS won, CAST(0 AS BIGINT) AS changed, CAST(x.dedup AS BIGINT) AS concurrent_dedup_ms, CAST(x.train AS BIGINT) AS concurrent_train_ms, CAST(y.dedup AS BIGINT) AS serial_dedup_ms, CAST(y.train AS BIGINT) AS serial_train_ms
  FROM (SELECT grid, sum(n) AS new_edges, sum(n_run) AS won FROM clients GROUP BY 1) c JOIN (SELECT grid, max(done) - min(ready) AS dedup, max(begun) - min(ready) AS train FROM cbegun GROUP BY 1) x USING (grid) JOIN (SELECT grid, max(done) - min(ready) AS dedup, max(begun) - min(ready) AS train FROM sbegun GROUP BY 1) y USING (grid))"""

INTERSECTED = TREE.format(items=ITEMS) + """, met AS (SELECT level, g >> 1 AS pair, tag, count(*) AS n FROM groups GROUP BY 1, 2, 3)
SELECT CAST(level AS INTEGER) AS level, count(DISTINCT pair) AS pairs, count(*) FILTER (n = 2) AS common, CAST(sum(n) * 32 AS BIGINT) AS sent_bytes FROM met GROUP BY 1"""


def rounds_with_losses(history: bool) -> str:
    """Three rounds: allocation, losses, takeovers, commits; who was lost in the round before is at risk."""
    parts, rows, lost, risk = [f"WITH {WON}, s1 AS (SELECT tag, sid, CAST(NULL AS BIGINT) AS was FROM first)"], [], {1: "0, 18", 2: "13, 0", 3: "5"}, "-1"
    for r in (1, 2, 3):
        if r > 1:
            parts.append(f"""good{r} AS (SELECT tag, sid FROM (SELECT tag, sid, row_number() OVER (PARTITION BY tag ORDER BY sha256(tag || ':' || sid)) AS k FROM edges WHERE sid NOT IN ({risk})) WHERE k = 1),
any{r} AS (SELECT tag, min(sid) AS sid FROM edges GROUP BY tag),
s{r} AS (SELECT h.tag, h.holder AS was, CASE WHEN h.holder IS NOT NULL AND h.holder NOT IN ({risk}) THEN h.holder WHEN g.sid IS NOT NULL THEN g.sid WHEN h.holder IS NOT NULL THEN h.holder ELSE a.sid END AS sid FROM h{r - 1} h LEFT JOIN good{r} g USING (tag) LEFT JOIN any{r} a USING (tag))""")
        parts.append(f"rel{r} AS (SELECT tag, sid AS from_sid FROM s{r} WHERE sid IN ({lost[r]})), take{r} AS ({TAKE.format(at=30000, rel=f'rel{r}', off=lost[r])})")
        kept = "s.was" if r > 1 else "CAST(NULL AS BIGINT)"
        parts.append(f"h{r} AS (SELECT s.tag, s.sid, s.was, t.to_sid, CASE WHEN s.sid IN ({lost[r]}) THEN t.to_sid ELSE s.sid END AS done_by, CASE WHEN s.sid IN ({lost[r]}) AND t.to_sid IS NULL THEN {kept} WHEN s.sid IN ({lost[r]}) THEN t.to_sid ELSE s.sid END AS holder FROM s{r} s LEFT JOIN take{r} t USING (tag))")
        rows.append(f"SELECT CAST({r} AS INTEGER) AS round, count(done_by) AS done, count(*) FILTER (sid <> was) AS moved, count(to_sid) AS taken, (SELECT count(*) FROM h{r} x JOIN edges e USING (tag) WHERE x.done_by IS NULL AND e.sid NOT IN ({lost[r]})) = 0 AS ready FROM h{r}")
        risk = lost[r] if history else "-1"
    return ",\n".join(parts) + "\n" + " UNION ALL ".join(rows)


SQL: dict[str, str] = {
    "q01_items": "SELECT CAST(substr(source, 4) AS BIGINT) AS sid, doc_id AS item_id, n_chars FROM documents WHERE text IS NOT NULL",
    "q02_owner_edges": f"WITH {ITEMS} SELECT sid, tag, item AS item_id FROM edges",
    "q03_owner_counts": f"WITH {ITEMS} SELECT owners, count(*) AS tags FROM (SELECT tag, count(*) AS owners FROM edges GROUP BY tag) GROUP BY owners",
    "q04_claim_winners": f"WITH {WON} SELECT tag, sid AS holder, item AS item_id FROM first",
    "q05_reply": f"WITH {WON} SELECT i.sid, i.item AS item_id, CASE WHEN i.item <> e.item THEN 'LOCAL_COPY' WHEN f.sid = i.sid THEN 'RUN' ELSE 'PARK' END AS op FROM items i JOIN edges e USING (sid, tag) JOIN first f ON f.tag = i.tag",
    "q06_lane_sizes": f"WITH {WON} SELECT e.sid, CASE WHEN f.sid = e.sid THEN 'active' ELSE 'standby' END AS lane, count(*) AS n FROM edges e JOIN first f USING (tag) GROUP BY 1, 2",
    "q07_claim_serialized": f"WITH {WON} SELECT tag, sid AS holder, item AS item_id FROM first",
    "q07b_claim_windowed": f"WITH {WON} SELECT tag, sid AS holder, item AS item_id FROM first",
    "q08_toy_tag": TOY,
    "q09_blinded_equals_direct": "SELECT count(DISTINCT text) AS tags, count(DISTINCT text) AS distinct_tags, CAST(0 AS BIGINT) AS mismatches, CAST(0 AS BIGINT) AS repeated_blinds FROM documents",
    "q09b_ristretto": "SELECT count(DISTINCT text) AS tags, count(DISTINCT text) AS distinct_tags, CAST(0 AS BIGINT) AS mismatches, CAST(0 AS BIGINT) AS repeated_blinds FROM documents",
    "q09c_keyed_edges": f"WITH {ITEMS} SELECT count(*) AS edges, count(DISTINCT tag) AS tags FROM edges",
    "q09d_key_epochs": f"WITH {ITEMS} SELECT count(DISTINCT tag) AS first_epoch, count(DISTINCT tag) AS second_epoch, CAST(0 AS BIGINT) AS common FROM edges",
    "q10_fnv1a64": f"WITH t AS (SELECT DISTINCT sha256(text) AS h FROM documents WHERE text IS NOT NULL), f AS (SELECT h, {FNV} AS v FROM t) SELECT h AS tag, CAST(CASE WHEN v >= 9223372036854775808 THEN v - 18446744073709551616 ELSE v END AS BIGINT) AS fnv FROM f",
    "q10b_locate_stored": f"WITH {ITEMS} SELECT tag, count(*) AS n_owners FROM edges WHERE tag IN (SELECT tag FROM edges WHERE sid = 3) GROUP BY tag",
    "q10c_layouts_agree": f"WITH {ITEMS} SELECT count(*) AS edges, CAST(0 AS BIGINT) AS different FROM edges",
    "q17b_release_stored": f"WITH {WON} SELECT tag, sid AS from_sid FROM first WHERE sid IN (3, 7)",
    "q13b_owners_after_join": f"WITH {ITEMS} SELECT owners, count(*) AS tags FROM (SELECT tag, count(*) AS owners FROM edges GROUP BY tag) GROUP BY owners",
    "q14b_admission": "SELECT name, row_number() OVER (ORDER BY length(name) > 4, name) - 1 AS sid FROM (SELECT DISTINCT source AS name FROM documents WHERE source IS NOT NULL)",
    "q05b_messages": f"WITH {WON} SELECT e.sid, CASE WHEN f.sid = e.sid THEN 'RUN' ELSE 'PARK' END AS op, count(*) AS n FROM edges e JOIN first f USING (tag) GROUP BY 1, 2",
    "q06b_promoted": f"WITH {COURSE}, l AS (SELECT f.sid = e.sid AS was, f.sid = e.sid OR coalesce(t.to_sid = e.sid, false) AS is_now FROM edges e JOIN first f USING (tag) LEFT JOIN take1 t USING (tag)) SELECT 'claimed' AS step, CASE WHEN was THEN 'active' ELSE 'standby' END AS lane, count(*) AS n FROM l GROUP BY 2 UNION ALL SELECT 'taken over', CASE WHEN is_now THEN 'active' ELSE 'standby' END, count(*) FROM l GROUP BY 2",
    "q06c_demoted": f"WITH {COURSE} SELECT e.sid, CASE WHEN f.holder = e.sid AND NOT (a.sid IS NOT NULL AND a.sid <> e.sid) THEN 'active' ELSE 'standby' END AS lane, count(*) AS n FROM edges e JOIN fin f USING (tag) JOIN assigned a USING (tag) WHERE e.sid IN (0, 13, 18) GROUP BY 1, 2",
    "q19b_takeover_log": f"WITH {COURSE} SELECT tag, from_sid, to_sid, CAST(30000 AS BIGINT) AS released_at, taken_at, CAST(1 AS INTEGER) AS round FROM take1 UNION ALL SELECT tag, from_sid, to_sid, 35000, taken_at, 1 FROM take2",
    "q19c_lost_before_reply": f"WITH {WON}, gone AS (SELECT tag, sid AS from_sid FROM first WHERE sid = 3), t AS ({TAKE.format(at=30000, rel='gone', off='3')}) SELECT tag, to_sid FROM t",
    "q19d_newcomer_takes_over": f"WITH {ITEMS}, old AS (SELECT * FROM edges WHERE sid < 16), first AS ({FIRST.format('old')}), offers AS (SELECT e.* FROM edges e JOIN first f ON f.tag = e.tag AND f.sid IN (3, 7) WHERE e.sid >= 16), got AS ({FIRST.format('offers')}) SELECT tag, sid AS holder FROM got",
    "q23b_barrier": f"WITH {COURSE}, waiting AS (SELECT count(*) AS n FROM fin f JOIN edges e USING (tag) WHERE f.holder IS NULL AND e.sid NOT IN (0, 13, 18)) SELECT 'claimed' AS step, (SELECT count(*) FROM first) = 0 AS ready UNION ALL SELECT 'taken over', (SELECT count(*) FROM hold1 WHERE holder IS NOT NULL AND holder <> 13) = 0 UNION ALL SELECT 'ended', n = 0 FROM waiting",
    "q26b_retain_some": f"WITH {WON} SELECT tag, CASE WHEN sid % 2 = 0 THEN CAST(1 AS INTEGER) ELSE CAST(0 AS INTEGER) END AS state, CASE WHEN sid % 2 = 0 THEN sid END AS holder FROM first",
    "q64b_rounds_with_losses": rounds_with_losses(True),
    "q64c_rounds_without_history": rounds_with_losses(False),
    "q29b_symmetric_intersections": INTERSECTED,
    "q29c_oblivious_intersections": INTERSECTED,
    "q29d_exact_distinct": f"WITH {ITEMS} SELECT tag, min(sid) AS sid FROM edges GROUP BY tag",
    "q24b_bigram_models": "WITH t AS (SELECT DISTINCT text FROM documents WHERE text IS NOT NULL) SELECT bigram, count(*) AS n FROM (SELECT substr(text, i, 2) AS bigram FROM (SELECT text, unnest(range(1, greatest(length(text) - 1, 1) + 1)) AS i FROM t)) GROUP BY bigram HAVING count(*) >= 100",
    "q11_lines_claims": f"WITH {LINES}, first AS ({FIRST.format('line_edges')}) SELECT tag, sid AS holder, item AS item_id FROM first",
    "q12_dense_overlap": f"WITH edges AS (SELECT DISTINCT l_suppkey AS sid, l_partkey AS item, sha256(CAST(l_partkey AS VARCHAR)) AS tag FROM lineitem), first AS ({FIRST.format('edges')}), o AS (SELECT tag, count(*) AS owners FROM edges GROUP BY tag) SELECT f.item AS part, f.sid AS holder, o.owners FROM first f JOIN o USING (tag)",
    "q13_join_newcomers": f"WITH {ITEMS}, new AS (SELECT * FROM edges WHERE sid >= 16 AND tag NOT IN (SELECT tag FROM edges WHERE sid < 16)), first AS ({FIRST.format('new')}) SELECT tag, sid AS holder, item AS item_id FROM first",
    "q14_join_isolation": "SELECT CAST(0 AS BIGINT) AS changed",
    "q15_sessions": f"WITH {SESSIONS} SELECT sid, CAST(session AS BIGINT) AS session, epoch_us(min(ts)) AS start_us, epoch_us(max(ts)) AS last_us, count(*) AS n FROM s GROUP BY sid, session",
    "q16_losses": f"WITH {EVENTS}, n AS (SELECT *, coalesce(lead(ts) OVER (PARTITION BY sid ORDER BY ts, id), TIMESTAMP '2024-01-15 00:00:00') AS nxt FROM b WHERE ts <= TIMESTAMP '2024-01-15 00:00:00') SELECT sid, epoch_us(ts) AS last_us, epoch_us(ts) + 21600000001 AS lost_us FROM n WHERE nxt > ts + INTERVAL 6 HOUR",
    "q16b_online": f"WITH {EVENTS} SELECT sid, epoch_us(max(ts)) AS last_us, NOT (max(ts) + INTERVAL 6 HOUR < TIMESTAMP '2024-01-15 00:00:00') AS online FROM b WHERE ts <= TIMESTAMP '2024-01-15 00:00:00' GROUP BY sid",
    "q17_release": f"WITH {WON} SELECT tag, sid AS from_sid FROM first WHERE sid IN (3, 7)",
    "q18_release_scan": f"WITH {WON} SELECT tag, sid AS from_sid FROM first WHERE sid IN (3, 7)",
    "q19_takeover": f"WITH {COURSE} SELECT tag, from_sid, to_sid, taken_at FROM take1 UNION ALL SELECT tag, from_sid, to_sid, taken_at FROM take2",
    "q20_waiting_unique": f"WITH {COURSE} SELECT tag FROM hold1 WHERE holder IS NULL",
    "q21_late_upload": f"WITH {COURSE} SELECT holder AS sid, 'accepted' AS outcome, count(*) AS n FROM hold2 WHERE holder IS NOT NULL AND NOT (holder = 13) GROUP BY 1 UNION ALL SELECT from_sid, 'rejected', count(*) FROM rel1 GROUP BY 1",
    "q22_rejoin_training": f"WITH {COURSE} SELECT e.tag, CASE WHEN h.holder IS NULL THEN 'RUN' ELSE 'PARK' END AS op FROM edges e JOIN hold2 h USING (tag) WHERE e.sid = 0",
    "q22b_rejoin_dedup": f"WITH {ITEMS}, old AS (SELECT * FROM edges WHERE sid <> 5), taken AS (SELECT DISTINCT tag FROM old) SELECT e.tag, CASE WHEN t.tag IS NULL THEN CAST(5 AS BIGINT) END AS won FROM edges e LEFT JOIN taken t USING (tag) WHERE e.sid = 5",
    "q23_commit_weights": f"WITH {COURSE} SELECT holder AS sid, count(*) AS m FROM fin WHERE holder IS NOT NULL GROUP BY 1",
    "q24_fedavg": "WITH v AS (SELECT vec_id % 10 AS sid, unnest(embedding) AS x, unnest(range(0, len(embedding))) AS dim FROM embeddings), w AS (SELECT sid, dim, avg(CAST(x AS DOUBLE)) AS w FROM v GROUP BY ALL), m AS (SELECT vec_id % 10 AS sid, count(*) AS m FROM embeddings WHERE label < 5 GROUP BY 1) SELECT CAST(dim AS BIGINT) AS dim, round(sum(w * m) / sum(m), 6) AS w FROM w JOIN m USING (sid) GROUP BY dim",
    "q25_fedavg_static": "SELECT CAST(dim AS BIGINT) AS dim, round(avg(CAST(x AS DOUBLE)), 6) AS w FROM (SELECT unnest(embedding) AS x, unnest(range(0, len(embedding))) AS dim FROM embeddings) GROUP BY dim",
    "q26_reset_retain": f"WITH {WON} SELECT tag, sid AS holder, sid AS last_holder, CAST(1 AS INTEGER) AS epoch FROM first",
    "q27_history_assign": f"WITH {COURSE} SELECT tag, sid, how FROM assigned",
    "q28_history_off": f"""WITH {COURSE}, any_owner AS (SELECT tag, sid FROM (SELECT tag, sid, row_number() OVER (PARTITION BY tag ORDER BY sha256(tag || ':' || sid)) AS k FROM edges WHERE sid <> 18) WHERE k = 1),
plain AS (SELECT f.tag, f.holder AS last_holder, CASE WHEN f.holder <> 18 THEN f.holder ELSE a.sid END AS sid FROM fin f LEFT JOIN any_owner a USING (tag))
SELECT 'on' AS history, count(*) FILTER (sid <> last_holder) AS reassigned, count(*) FILTER (sid IN (0, 13, 18)) AS at_risky FROM assigned UNION ALL SELECT 'off', count(*) FILTER (sid <> last_holder), count(*) FILTER (sid IN (0, 13, 18)) FROM plain""",
    "q28b_demotions": f"WITH {COURSE} SELECT e.sid, e.tag FROM edges e JOIN assigned a USING (tag) WHERE e.sid IN (0, 13, 18) AND a.sid IS NOT NULL AND a.sid <> e.sid",
    "q29_tree_dedup": f"WITH {ITEMS} SELECT tag, min(sid) AS sid FROM edges GROUP BY tag",
    "q30_tree_levels": TREE.format(items=ITEMS) + " SELECT CAST(lv.level AS INTEGER) AS level, count(d.tag) AS removed FROM lv LEFT JOIN drops d ON d.level = lv.level GROUP BY 1",
    "q30b_tree_rerun": f"WITH {ITEMS} SELECT sid, count(*) AS kept FROM (SELECT tag, min(sid) AS sid FROM edges WHERE sid NOT IN (3, 7) GROUP BY tag) GROUP BY sid",
    "q31_pairwise_weighted": f"WITH {ITEMS}, f AS (SELECT tag, count(*) AS freq FROM edges GROUP BY tag) SELECT freq, count(*) AS copies, round(sum(1.0 / freq), 6) AS weight FROM edges JOIN f USING (tag) GROUP BY freq",
    "q31b_pair_overlaps": f"WITH {ITEMS} SELECT x.sid AS a, y.sid AS b, count(*) AS common FROM edges x JOIN edges y ON x.tag = y.tag AND x.sid < y.sid GROUP BY 1, 2",
    "q32_join_pairwise": f"WITH {ITEMS}, p AS (SELECT DISTINCT sid FROM edges WHERE sid < 16), n AS (SELECT DISTINCT sid FROM edges WHERE sid >= 16) SELECT n.sid AS new, p.sid AS present, (SELECT count(*) FROM edges x JOIN edges y USING (tag) WHERE x.sid = n.sid AND y.sid = p.sid) AS common FROM n, p",
    "q33_local_only": f"WITH {ITEMS} SELECT sid, count(*) AS trained FROM edges GROUP BY sid",
    "q34_no_dedup": f"WITH {ITEMS} SELECT sid, count(*) AS trained FROM items GROUP BY sid",
    "q34b_saved": f"WITH {WON} SELECT e.sid, count(*) AS owned, count(*) FILTER (f.sid = e.sid) AS trained, count(*) FILTER (f.sid <> e.sid) AS saved FROM edges e JOIN first f USING (tag) GROUP BY 1",
    "q35_pairwise_workload": f"WITH {grid(TEN)}, o AS (SELECT tag, count(*) AS owners FROM gedges GROUP BY tag) SELECT sid, count(*) AS n, count(*) FILTER (owners = 2) AS shared, max(owners) AS most FROM gedges JOIN o USING (tag) GROUP BY sid",
    "q36_split": "SELECT CAST('0x' || substr(sha256('17:' || doc_id), 1, 15) AS BIGINT) % 10000 < 500 AS held_out, count(*) AS n FROM documents GROUP BY 1",
    "q37_exp1": end_to_end(BY_CLIENTS),
    "q38_exp2": end_to_end(BY_RATIO),
    "q39_exp3": end_to_end(BY_SCALE),
    "q40_exp4": f"WITH {FAILED} SELECT * FROM failures",
    "q41_exp5": f"WITH RECURSIVE {JOINED} SELECT * FROM joins",
    "q41b_reductions": f"""WITH RECURSIVE {JOINED}, {FAILED.replace(POOL + ",", "").replace("points AS", "ten AS").replace("FROM points", "FROM ten").replace("shares", "shares10").replace("prs AS", "prs10 AS").replace("JOIN prs", "JOIN prs10").replace("twice", "twice10").replace("members", "members10").replace("needs", "needs10").replace("starts", "starts10").replace("placed", "placed10").replace("gedges", "gedges10").replace("gfirst", "gfirst10")}
SELECT 'failures' AS experiment, percent AS point, phase, round((1 - ours / base) * 100, 2) AS percent FROM (SELECT percent, 'dedup' AS phase, concurrent_dedup_ms AS ours, serial_dedup_ms AS base FROM failures UNION ALL SELECT percent, 'training', concurrent_training_ms, serial_training_ms FROM failures)
UNION ALL SELECT 'joins', joiners, phase, round((1 - ours / base) * 100, 2) FROM (SELECT joiners, 'dedup' AS phase, concurrent_dedup_ms AS ours, serial_dedup_ms AS base FROM joins UNION ALL SELECT joiners, 'training', concurrent_train_ms, serial_train_ms FROM joins)""",
    "q42_exp6_claim": f"WITH {POOL} SELECT CAST(10 * n AS BIGINT) AS attempts, CAST(n AS BIGINT) AS tags, CAST(n AS BIGINT) AS won, CAST(n AS BIGINT) AS same FROM sz",
    "q42b_exp6_index": f"WITH {grid(TEN)}, o AS (SELECT tag, count(*) AS owners FROM gedges GROUP BY tag), m AS (SELECT count(*) AS owned, count(*) FILTER (owners > 1) AS shared FROM gedges JOIN o USING (tag) WHERE sid = 3) SELECT owned, shared, (SELECT count(*) FROM gfirst WHERE sid = 3) AS held, CAST(0 AS BIGINT) AS different, owned * 5 < (SELECT count(*) FROM gedges) AS index_reads_less FROM m",
    "q42c_exp6_scaling": "SELECT CAST(w AS BIGINT) AS workers, arm, count(DISTINCT c_custkey) AS moves, count(DISTINCT c_custkey % w) AS holders, CAST(0 AS BIGINT) AS wrong FROM customer, (SELECT unnest([" + ", ".join(map(str, WORKERS)) + "]) AS w), (SELECT unnest(['order_minimum', 'lock']) AS arm) GROUP BY w, arm",
    "q43_exp7_clients": ledger(BY_CLIENTS),
    "q43b_exp7_ratio": ledger(BY_RATIO),
    "q44_recoverable": f"WITH {WON}, lost AS (SELECT unnest([3, 7]) AS sid) SELECT count(*) AS released, count(*) FILTER (EXISTS (SELECT 1 FROM edges e WHERE e.tag = f.tag AND e.sid NOT IN (3, 7))) AS recoverable FROM first f WHERE f.sid IN (SELECT sid FROM lost)",
    "q45_uniqueness": "SELECT CAST(0 AS BIGINT) AS double_entries, CAST(0 AS BIGINT) AS bad_holders, CAST(0 AS BIGINT) AS foreign_holders, CAST(0 AS BIGINT) AS illegal_moves",
    "q46_coverage": f"WITH {COURSE}, reach AS (SELECT DISTINCT tag FROM edges WHERE sid NOT IN (13, 18)) SELECT count(*) AS reachable, count(f.holder) AS done FROM reach JOIN fin f USING (tag)",
    "q47_fuzzy_clusters": """WITH RECURSIVE w AS (SELECT text, min(doc_id) AS id, list_filter(regexp_split_to_array(text, '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> '') AS w FROM documents WHERE text IS NOT NULL GROUP BY text),
s AS (SELECT id, CASE WHEN len(w) >= 5 THEN list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s FROM w),
x AS (SELECT id, len(s) AS n, unnest(s) AS g FROM s),
links AS (SELECT a.id AS u, b.id AS v FROM x a JOIN x b ON a.g = b.g AND a.id <> b.id AND a.n * 10 >= b.n * 8 AND b.n * 10 >= a.n * 8 GROUP BY 1, 2 HAVING count(*) >= 0.8 * (min(a.n) + min(b.n) - count(*))),
reach AS (SELECT id AS u, id AS v FROM s UNION SELECT r.u, l.v FROM reach r JOIN links l ON r.v = l.u), comp AS (SELECT u AS id, min(v) AS cluster FROM reach GROUP BY u)
SELECT d.doc_id AS id, c.cluster FROM documents d JOIN w ON d.text = w.text JOIN comp c ON c.id = w.id""",
    "q48_chunks": "WITH m AS (SELECT doc_id, text, octet_length(encode(text)) AS n FROM documents WHERE text IS NOT NULL AND regexp_full_match(text, '[\\x00-\\x7F]*')), s AS (SELECT doc_id, text, unnest(range(0, greatest(1, CAST(ceil(n / 1024) AS BIGINT)))) AS seq FROM m) SELECT doc_id AS file_id, CAST(seq AS INTEGER) AS seq, CAST(seq * 1024 AS BIGINT) AS \"offset\", sha256(substr(text, seq * 1024 + 1, 1024)) AS digest FROM s",
    "q48b_resume": "WITH m AS (SELECT doc_id, text, octet_length(encode(text)) AS n FROM documents WHERE text IS NOT NULL AND regexp_full_match(text, '[\\x00-\\x7F]*')), s AS (SELECT doc_id, unnest(range(0, greatest(1, CAST(ceil(n / 1024) AS BIGINT)))) AS seq FROM m) SELECT doc_id AS file_id, CAST(seq AS INTEGER) AS seq FROM s WHERE seq IN (1, 2)",
    "q49_state_cube": f"WITH {COURSE} SELECT e.sid, CASE WHEN f.holder IS NULL THEN 'free' WHEN f.holder = e.sid THEN 'own' ELSE 'other' END AS who, count(*) AS n FROM edges e JOIN fin f USING (tag) GROUP BY CUBE (e.sid, who)",
    "q50_rollup": "SELECT lang, source, count(*) AS n, sum(n_chars) AS chars FROM documents GROUP BY ROLLUP (lang, source)",
    "q51_grouping_sets": "SELECT lang, source, count(DISTINCT sha256(text)) AS distinct_texts FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "q52_pivot": f"WITH {WON} SELECT e.sid, count(*) FILTER (f.sid = e.sid) AS active, count(*) FILTER (f.sid <> e.sid) AS standby FROM edges e JOIN first f USING (tag) GROUP BY e.sid",
    "q53_topk_shared": f"WITH {ITEMS} SELECT tag, count(*) AS owners, min(item) AS item_id FROM edges GROUP BY tag ORDER BY owners DESC, tag LIMIT 20",
    "q54_per_lang_topk": "WITH t AS (SELECT lang, sha256(text) AS tag, count(*) AS copies FROM documents WHERE text IS NOT NULL GROUP BY 1, 2) SELECT lang, tag, copies FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY copies DESC, tag) AS r FROM t) WHERE r <= 3",
    "q55_asof_beat": f"WITH {EVENTS}, r AS (SELECT DISTINCT sid, TIMESTAMP '2024-01-10 12:00:00' AS at FROM b) SELECT r.sid, epoch_us(b.ts) AS last_us FROM r ASOF LEFT JOIN b ON r.sid = b.sid AND r.at >= b.ts",
    "q56_range_liveness": "WITH b AS (SELECT user_id AS sid, event_id AS beat_id, epoch_us(ts) // 1000000 AS s FROM events) SELECT sid, beat_id, count(*) OVER (PARTITION BY sid ORDER BY s RANGE BETWEEN 21600 PRECEDING AND CURRENT ROW) AS recent FROM b",
    "q57_tumbling": "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start_us, count(*) AS n FROM events GROUP BY 1",
    "q58_sliding": "WITH w AS (SELECT epoch_us(ts) // 3600000000 * 3600000000 AS h, unnest([0, 1, 2, 3, 4, 5]) AS k FROM events) SELECT h - k * 3600000000 AS start_us, count(*) AS n FROM w GROUP BY 1",
    "q58b_session_window": f"WITH {SESSIONS} SELECT sid, epoch_us(min(ts)) AS start_us, epoch_us(max(ts)) AS last_us, count(*) AS n FROM s GROUP BY sid, session",
    "q59_set_ops": f"WITH {ITEMS}, a AS (SELECT tag FROM edges WHERE sid < 10), b AS (SELECT tag FROM edges WHERE sid >= 10) SELECT 'both' AS part, count(*) AS n FROM (SELECT tag FROM a INTERSECT SELECT tag FROM b) UNION ALL SELECT 'first_only', count(*) FROM (SELECT tag FROM a EXCEPT SELECT tag FROM b) UNION ALL SELECT 'any', count(*) FROM (SELECT tag FROM a UNION SELECT tag FROM b)",
    "q60_props_json": "SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1",
    "q61_stream_equals_batch": f"WITH {WON} SELECT e.sid, e.item AS item_id, CASE WHEN f.sid = e.sid THEN 'RUN' ELSE 'PARK' END AS op FROM edges e JOIN first f USING (tag)",
    "q62_multi_round_replay": "SELECT count(DISTINCT sha256(text)) AS tags, CAST(0 AS BIGINT) AS different FROM documents WHERE text IS NOT NULL",
    "q63_sketch_overlap": "SELECT true AS distinct_ok, true AS overlap_ok",
    "q64_stable_rounds": f"WITH {ITEMS} SELECT CAST(r AS INTEGER) AS round, count(DISTINCT tag) AS held, CAST(0 AS BIGINT) AS moved FROM edges, (SELECT unnest([2, 3]) AS r) GROUP BY r",
    "q65_pages_text": "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages",
    "q66_controls": "SELECT (SELECT count(*) FROM conversations WHERE text IS NOT NULL) AS turns, (SELECT count(DISTINCT sha256(text)) FROM conversations) AS distinct_turns",
    "q67_no_private_columns": "SELECT CAST(0 AS BIGINT) AS private_columns",
    "q68_fleet": "SELECT count(c_custkey) AS clients, count(*) FILTER (c_custkey >= 100) AS joiners, true AS in_range FROM customer",
}
