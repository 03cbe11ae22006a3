"""Histories over the given tables as SQL that Spark and DuckDB both run; only a few functions differ by dialect."""

from __future__ import annotations

DIALECTS = {
    "spark": {"us": "unix_micros(cast({} as timestamp))", "k": "cast(get_json_object(props, '$.k') as bigint)", "last": "last_value({}, true)", "str": "string"},
    "duckdb": {"us": "epoch_us({})", "k": "cast(props->>'$.k' as bigint)", "last": "last_value({} IGNORE NULLS)", "str": "varchar"},
}
#: Writer blocks out of ten for the read-heavy, half-and-half and write-heavy mixes.
WRITERS = {"rh": 2, "wr": 5, "wh": 8}
SESSIONS, BLOCK, ROWS = 24, 8, 10_000


def registers(dialect: str, mix: str, level: str = "serial", sessions: int = SESSIONS, block: int = BLOCK) -> str:
    """CTEs txns and ops: blocks of events as read-only or write-only transactions on single rows, with what reads observe
    at an isolation level: serial (order of end times), snapshot (as of the start), rc (as of the operation, committed
    transactions only) or ru (as of the operation, aborted writes included; every eleventh writer block aborts)."""
    d = DIALECTS[dialect]
    status = "CASE WHEN kind = 'w' AND txn_id % 11 = 7 THEN 'a' ELSE 'c' END" if level in ("rc", "ru") else "'c'"
    #: when a write can be seen, and when a read looks
    seen, looks = {"serial": ("e", "e"), "snapshot": ("e", "s"), "rc": ("e", "us"), "ru": ("us", "us")}[level]
    shown = "kind = 'w' AND status = 'c'" if level == "rc" else "kind = 'w'"
    return f"""
ev AS (SELECT event_id, {d["us"].format("ts")} AS us, event_id % {sessions} AS session_id, {d["k"]} AS k,
         row_number() OVER (PARTITION BY event_id % {sessions} ORDER BY ts, event_id) - 1 AS rk FROM events),
np AS (SELECT least(count(*), {ROWS}) AS n FROM part),
bl AS (SELECT ev.*, cast(floor((rk + session_id) / {block}.0) AS bigint) AS block, (event_id * 7919 + k * 104729) % np.n AS o FROM ev, np),
op0 AS (SELECT session_id * 1000000 + block + 1 AS txn_id, block, session_id, us, event_id,
         row_number() OVER (PARTITION BY session_id, block ORDER BY us, event_id) AS op_seq,
         CASE WHEN (block * 7 + session_id) % 10 < {WRITERS[mix]} THEN 'w' ELSE 'r' END AS kind, concat('part:', cast(o AS {d["str"]})) AS obj FROM bl),
op1 AS (SELECT *, {status} AS status, min(us) OVER (PARTITION BY txn_id) AS s, max(us) OVER (PARTITION BY txn_id) + 1 AS e FROM op0),
tx AS (SELECT txn_id, session_id, block AS session_pos, max(status) AS own, min(s) AS s, max(e) AS e, max(kind) AS ttype FROM op1 GROUP BY txn_id, session_id, block),
op2 AS (SELECT *, CASE WHEN {shown} THEN event_id + 1 END AS shows, CASE WHEN kind = 'w' THEN {seen} ELSE {looks} END AS tm, CASE WHEN kind = 'w' THEN 0 ELSE 1 END AS later FROM op1),
op3 AS (SELECT *, {d["last"].format("shows")} OVER (PARTITION BY obj ORDER BY tm, {"later, txn_id" if level != "serial" else "txn_id, later"}, op_seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS sees FROM op2),
txns AS (SELECT cast(txn_id AS bigint) AS txn_id, cast(session_id AS int) AS session_id, cast(session_pos AS int) AS session_pos, CASE WHEN ttype = 'w' THEN own ELSE 'c' END AS status, s, e, ttype
  FROM (SELECT txn_id, session_id, session_pos, min(own) AS own, min(s) AS s, max(e) AS e, max(ttype) AS ttype FROM tx GROUP BY txn_id, session_id, session_pos) q),
ops AS (SELECT cast(txn_id AS bigint) AS txn_id, cast(op_seq AS int) AS op_seq, kind, obj, cast(CASE WHEN kind = 'w' THEN event_id + 1 ELSE coalesce(sees, 0) END AS bigint) AS ver, us AS op_s, us + 1 AS op_e FROM op3)"""


def orders_mix(dialect: str) -> str:
    """CTEs txns and ops: an order-entry mix over one warehouse, by o_orderkey % 100; reads observe the serial order of end times."""
    d = DIALECTS[dialect]
    return f"""
od AS (SELECT o_orderkey AS k, o_custkey AS c, {d["us"].format("o_orderdate")} + (o_orderkey % 86400) * 1000000 AS s, o_orderkey % 100 AS m FROM orders),
tx AS (SELECT k, c, s, s + (1 + k % 7) * 900000000 AS e, CASE WHEN m < 45 THEN 'new_order' WHEN m < 88 THEN 'payment' WHEN m < 92 THEN 'order_status' WHEN m < 96 THEN 'delivery' ELSE 'stock_level' END AS ttype FROM od),
st AS (SELECT DISTINCT l_orderkey AS k, l_partkey AS p FROM lineitem),
op0 AS (
  SELECT tx.*, 'r' AS kind, concat('stock:', cast(p AS {d["str"]})) AS obj, 1 AS grp FROM tx JOIN st ON st.k = tx.k WHERE ttype IN ('new_order', 'stock_level')
  UNION ALL SELECT tx.*, 'w', concat('stock:', cast(p AS {d["str"]})), 2 FROM tx JOIN st ON st.k = tx.k WHERE ttype = 'new_order'
  UNION ALL SELECT tx.*, 'r', concat('district:', cast(c % 10 AS {d["str"]})), 3 FROM tx WHERE ttype IN ('new_order', 'payment', 'stock_level')
  UNION ALL SELECT tx.*, 'w', concat('district:', cast(c % 10 AS {d["str"]})), 4 FROM tx WHERE ttype IN ('new_order', 'payment')
  UNION ALL SELECT tx.*, 'r', concat('customer:', cast(c AS {d["str"]})), 5 FROM tx WHERE ttype IN ('payment', 'order_status')
  UNION ALL SELECT tx.*, 'w', concat('customer:', cast(c AS {d["str"]})), 6 FROM tx WHERE ttype IN ('payment', 'delivery')
  UNION ALL SELECT tx.*, 'r', 'warehouse', 7 FROM tx WHERE ttype = 'payment'
  UNION ALL SELECT tx.*, 'w', 'warehouse', 8 FROM tx WHERE ttype = 'payment'),
op1 AS (SELECT k + 1 AS txn_id, row_number() OVER (PARTITION BY k ORDER BY grp, obj) AS op_seq, kind, obj, s, e FROM op0),
op2 AS (SELECT *, {d["last"].format("CASE WHEN kind = 'w' THEN txn_id * 1000 + op_seq END")} OVER (PARTITION BY obj ORDER BY e, txn_id, op_seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS sees FROM op1),
txns AS (SELECT k + 1 AS txn_id, cast(c % 16 AS int) AS session_id, cast(0 AS int) AS session_pos, 'c' AS status, s, e, ttype FROM tx),
ops AS (SELECT txn_id, cast(op_seq AS int) AS op_seq, kind, obj, cast(CASE WHEN kind = 'w' THEN txn_id * 1000 + op_seq ELSE coalesce(sees, 0) END AS bigint) AS ver, s AS op_s, e AS op_e FROM op2)"""


def social(dialect: str) -> str:
    """CTEs txns and ops: posts, follows and timeline reads of few hot users; a transaction is an event and its user's next one."""
    d = DIALECTS[dialect]
    return f"""
ev AS (SELECT event_id, {d["us"].format("ts")} AS us, user_id % 16 AS hot, user_id, event_type, event_id % 12 AS session_id,
         row_number() OVER (PARTITION BY event_id % 12 ORDER BY ts, event_id) - 1 AS rk FROM events),
op0 AS (SELECT session_id * 1000000 + cast(floor((rk + session_id) / 4.0) AS bigint) + 1 AS txn_id, session_id, cast(floor((rk + session_id) / 4.0) AS bigint) AS session_pos, us, event_id,
         CASE WHEN event_id % 3 = 0 THEN 'w' ELSE 'r' END AS kind,
         CASE WHEN event_id % 3 = 0 THEN concat('post:', cast(hot AS {d["str"]})) WHEN event_id % 3 = 1 THEN concat('timeline:', cast(user_id AS {d["str"]})) ELSE concat('post:', cast((hot * 7 + 3) % 16 AS {d["str"]})) END AS obj FROM ev),
op1 AS (SELECT *, row_number() OVER (PARTITION BY txn_id ORDER BY us, event_id) AS op_seq, min(us) OVER (PARTITION BY txn_id) AS s, max(us) OVER (PARTITION BY txn_id) + 1 AS e FROM op0),
op2 AS (SELECT *, {d["last"].format("CASE WHEN kind = 'w' THEN event_id + 1 END")} OVER (PARTITION BY obj ORDER BY e, txn_id, op_seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS sees FROM op1),
txns AS (SELECT txn_id, cast(session_id AS int) AS session_id, cast(session_pos AS int) AS session_pos, 'c' AS status, min(s) AS s, max(e) AS e, 'social' AS ttype FROM op1 GROUP BY txn_id, session_id, session_pos),
ops AS (SELECT txn_id, cast(op_seq AS int) AS op_seq, kind, obj, cast(CASE WHEN kind = 'w' THEN event_id + 1 ELSE coalesce(sees, 0) END AS bigint) AS ver, us AS op_s, us + 1 AS op_e FROM op2)"""


def predicate_parts(dialect: str) -> tuple[str, str, str]:
    """CTEs txns, ops, vers and prs: half the blocks of four events write rows of part (the first 10,000 at most, v1 its size, v2 its
    price), half read by range predicates on v1 or v2, one for each event; each read returns, of every row, the version that the
    serial order of end times shows, if it matches. In three parts: rows of part, the events as operations (op1), and what follows
    from both."""
    d = DIALECTS[dialect]
    text = lambda x: f"concat('prow:', cast({x} AS {d['str']}))"
    rows = f"""
rows0 AS (SELECT row_number() OVER (ORDER BY p_partkey) AS o, cast(p_size AS double) AS v1, cast(p_retailprice AS double) AS v2 FROM part),
objs AS (SELECT * FROM rows0 WHERE o <= {ROWS})"""
    events = f"""
np AS (SELECT count(*) AS n FROM objs),
ev AS (SELECT event_id, {d["us"].format("ts")} AS us, cast(floor(abs(coalesce(value, 0))) AS bigint) AS val, (event_id * 7919 + {d["k"]} * 104729) % np.n + 1 AS o, event_id % 12 AS session_id,
         row_number() OVER (PARTITION BY event_id % 12 ORDER BY ts, event_id) - 1 AS rk FROM events, np),
op0 AS (SELECT *, session_id * 1000000 + cast(floor((rk + session_id) / 4.0) AS bigint) + 1 AS txn_id, cast(floor((rk + session_id) / 4.0) AS bigint) AS block FROM ev),
op1 AS (SELECT *, CASE WHEN (block * 7 + session_id) % 10 < 5 THEN 'w' ELSE 'pr' END AS kind, min(us) OVER (PARTITION BY txn_id) AS s, max(us) OVER (PARTITION BY txn_id) + 1 AS e,
         row_number() OVER (PARTITION BY txn_id ORDER BY us, event_id) AS op_seq,
         1 + (event_id * 31 + val) % 50 AS a1, 900 + (event_id * 7919 + val) % 1200 AS a2, cast(floor(event_id / 12.0) AS bigint) % 2 AS which FROM op0)"""
    follows = f"""
asked AS (SELECT txn_id, e, cast(event_id AS int) AS pred_id, CASE WHEN which = 0 THEN 'v1' ELSE 'v2' END AS col, cast(CASE WHEN which = 0 THEN a1 ELSE a2 END AS double) AS lo,
         cast(CASE WHEN which = 0 THEN a1 + a2 % 6 ELSE a2 + a1 * 2 END AS double) AS hi FROM op1 WHERE kind = 'pr'),
prs AS (SELECT pred_id, 'prow' AS domain, col, lo, hi FROM asked),
vers AS (SELECT {text("o")} AS obj, cast(0 AS bigint) AS ver, cast(0 AS bigint) AS txn_id, v1, v2, false AS deleted FROM objs
  UNION ALL SELECT {text("o")}, event_id + 1, txn_id, cast(a1 AS double), cast(a2 AS double), false FROM op1 WHERE kind = 'w'),
wrote AS (SELECT {text("o")} AS obj, cast(0 AS bigint) AS ver, cast(-4611686018427387904 AS bigint) AS e, cast(0 AS bigint) AS txn_id, 0 AS op_seq, v1, v2 FROM objs
  UNION ALL SELECT {text("o")}, event_id + 1, e, txn_id, op_seq, cast(a1 AS double), cast(a2 AS double) FROM op1 WHERE kind = 'w'),
shown AS (SELECT *, lead(e) OVER (PARTITION BY obj ORDER BY e, txn_id, op_seq) AS next_e, lead(txn_id) OVER (PARTITION BY obj ORDER BY e, txn_id, op_seq) AS next_txn FROM wrote),
hits AS (SELECT a.txn_id, a.pred_id, v.obj, v.ver AS sees FROM asked a JOIN shown v ON CASE WHEN a.col = 'v1' THEN v.v1 ELSE v.v2 END BETWEEN a.lo AND a.hi
  AND (v.e < a.e OR v.e = a.e AND v.txn_id < a.txn_id) AND (v.next_e IS NULL OR v.next_e > a.e OR v.next_e = a.e AND v.next_txn > a.txn_id)),
txns AS (SELECT txn_id, cast(session_id AS int) AS session_id, cast(block AS int) AS session_pos, 'c' AS status, min(s) AS s, max(e) AS e, max(kind) AS ttype FROM op1 GROUP BY txn_id, session_id, block),
ops AS (SELECT txn_id, cast(op_seq AS int) AS op_seq, kind, {text("o")} AS obj, event_id + 1 AS ver, cast(NULL AS int) AS pred_id FROM op1 WHERE kind = 'w'
  UNION ALL SELECT txn_id, 0, 'pr', obj, sees, pred_id FROM hits
  UNION ALL SELECT a.txn_id, 0, 'pr', NULL, NULL, a.pred_id FROM asked a WHERE NOT EXISTS (SELECT 1 FROM hits h WHERE h.txn_id = a.txn_id AND h.pred_id = a.pred_id))"""
    return rows, events, follows


def predicate_rows(dialect: str) -> str:
    """CTEs txns, ops, vers and prs, see predicate_parts()."""
    return ",".join(predicate_parts(dialect))
