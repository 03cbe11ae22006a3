"""Registered queries of the verifier and the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.baselines import polygraph, protocol, small
from orderproof.histories import build, cases, fixtures, inject, schedulers, texts
from orderproof.operators import complete, dense, deps, encodings, prelim
from orderproof.operators import constraints as cs
from orderproof.plans import islands, measures, verify
from orderproof.plans.bounds import bounds, layout
from orderproof.sources.scratch import scope, written
from orderproof.streaming import live

QUERIES: dict = {}
ORACLES: dict = {}

#: Shared by the oracles: committed transactions, installed versions and reads of the history before them.
BASE = """
com AS (SELECT txn_id, s, e FROM txns WHERE status = 'c'),
inst AS (SELECT w.txn_id, w.obj, w.ver, c.s, c.e FROM (SELECT txn_id, obj, arg_max(ver, op_seq) AS ver FROM ops WHERE kind = 'w' GROUP BY ALL) w JOIN com c USING (txn_id)),
rd AS (SELECT DISTINCT o.txn_id, o.obj, o.ver, c.s, c.e FROM ops o JOIN com c USING (txn_id) WHERE o.kind <> 'w')"""


def _add(name: str, run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def _on(name: str, ctes: str, make, run, select: str) -> None:
    """A query over one history: run(H) in Spark, `select` over its tables and BASE in SQL."""
    _add(name, lambda spark, d: run(make(spark, d)), f"WITH {ctes}, {BASE}\n{select}")


def _reg(mix: str, level: str = "serial"):
    return lambda spark, d: build.registers(spark, d, mix, level)


WR, RU = texts.registers("duckdb", "wr"), texts.registers("duckdb", "wr", "ru")
OPS = "SELECT txn_id, op_seq, kind, obj, ver FROM ops"
ops = lambda h: h.ops.select("txn_id", "op_seq", "kind", "obj", "ver")

# -- histories
for m in ("rh", "wr", "wh"):
    _on(f"reg_{m}_ops", texts.registers("duckdb", m), _reg(m), ops, OPS)
for lv, label in (("snapshot", "sim_snapshot_reads"), ("rc", "sim_read_committed"), ("ru", "sim_read_uncommitted")):
    _on(label, texts.registers("duckdb", "wr", lv), _reg("wr", lv), ops, OPS)
_on("ord_txns", texts.orders_mix("duckdb"), build.orders_mix, lambda h: h.txns.select("txn_id", "s", "e", "ttype"), "SELECT txn_id, s, e, ttype FROM txns")
_on("ord_ops", texts.orders_mix("duckdb"), build.orders_mix, ops, OPS)
_on("soc_ops", texts.social("duckdb"), build.social, ops, OPS)

# -- what a history says by itself
_on("committed_txns", RU, _reg("wr", "ru"), lambda h: prelim.committed(h).select("txn_id", "s", "e"), "SELECT txn_id, s, e FROM com")
_on("installed_versions", WR, _reg("wr"), lambda h: prelim.installed(h).select("txn_id", "obj", "ver"), "SELECT txn_id, obj, ver FROM inst")
_on("aborted_reads", RU, _reg("wr", "ru"), prelim.aborted_reads, """SELECT rd.txn_id AS reader, o.txn_id AS writer, rd.obj, rd.ver FROM rd JOIN ops o ON o.kind = 'w' AND o.obj = rd.obj AND o.ver = rd.ver
  JOIN txns t ON t.txn_id = o.txn_id AND t.status = 'a'""")
_on("intermediate_reads", RU, _reg("wr", "ru"), prelim.intermediate_reads, """SELECT DISTINCT rd.txn_id AS reader, o.txn_id AS writer, rd.obj, rd.ver FROM rd JOIN ops o ON o.kind = 'w' AND o.obj = rd.obj AND o.ver = rd.ver
  JOIN com c ON c.txn_id = o.txn_id WHERE rd.txn_id <> o.txn_id AND NOT EXISTS (SELECT 1 FROM inst i WHERE i.txn_id = o.txn_id AND i.obj = o.obj AND i.ver = o.ver)""")
_on("orphan_reads", RU, _reg("wr", "ru"), prelim.orphan_reads, "SELECT txn_id AS reader, obj, ver FROM rd WHERE ver <> 0 AND NOT EXISTS (SELECT 1 FROM ops o WHERE o.kind = 'w' AND o.obj = rd.obj AND o.ver = rd.ver)")
_on("duplicate_versions", WR, _reg("wr"), prelim.duplicate_versions, "SELECT obj, ver, count(*) AS n FROM ops WHERE kind = 'w' GROUP BY ALL HAVING count(*) > 1")

# -- predicates
PRED = texts.predicate_rows("duckdb")
THETA = "th AS (SELECT p.pred_id, v.obj, v.ver, CASE WHEN p.col = 'v1' THEN v.v1 ELSE v.v2 END BETWEEN p.lo AND p.hi AS holds FROM prs p, vers v)"
UNK = """asks AS (SELECT DISTINCT txn_id, pred_id FROM ops WHERE kind = 'pr'), allr AS (SELECT a.txn_id, a.pred_id, o.obj FROM asks a, (SELECT DISTINCT obj FROM vers) o),
tr AS (SELECT a.*, o.ver FROM allr a LEFT JOIN ops o ON o.kind = 'pr' AND o.txn_id = a.txn_id AND o.pred_id = a.pred_id AND o.obj = a.obj)"""
OPEN = """rel AS (SELECT DISTINCT pred_id, obj FROM th WHERE holds),
unk AS (SELECT a.txn_id AS reader, a.pred_id, r.obj FROM (SELECT DISTINCT txn_id, pred_id FROM ops WHERE kind = 'pr') a JOIN rel r ON r.pred_id = a.pred_id
  WHERE NOT EXISTS (SELECT 1 FROM ops o WHERE o.kind = 'pr' AND o.txn_id = a.txn_id AND o.pred_id = a.pred_id AND o.obj = r.obj))"""
CAND = """few AS (SELECT DISTINCT pred_id, obj FROM unk),
wr AS (SELECT i.obj, th.pred_id, i.txn_id, th.holds FROM few JOIN th ON th.pred_id = few.pred_id AND th.obj = few.obj JOIN inst i ON i.obj = th.obj AND i.ver = th.ver
  UNION ALL SELECT th.obj, th.pred_id, 0, holds FROM few JOIN th ON th.pred_id = few.pred_id AND th.obj = few.obj WHERE ver = 0),
fa AS (SELECT u.reader, u.pred_id, u.obj, w.txn_id AS cand FROM unk u JOIN wr w ON w.obj = u.obj AND w.pred_id = u.pred_id AND NOT w.holds WHERE w.txn_id <> u.reader),
op AS (SELECT f.reader, f.obj, f.cand, w.txn_id AS dst FROM fa f JOIN wr w ON w.obj = f.obj AND w.pred_id = f.pred_id AND w.holds WHERE w.txn_id <> f.cand AND w.txn_id <> 0 AND w.txn_id <> f.reader)"""
#: Versions of each object in order, the initial one at place 0, with the truth of each predicate that some version meets.
FLIPS = """vo AS (SELECT obj, ver, txn_id, e, row_number() OVER (PARTITION BY obj ORDER BY e, txn_id) AS pos FROM inst UNION ALL SELECT obj, ver, 0, -4611686018427387904, 0 FROM vers WHERE ver = 0),
fl AS (SELECT th.pred_id, th.obj, vo.pos, vo.txn_id, vo.e, th.holds <> coalesce(lag(th.holds) OVER (PARTITION BY th.pred_id, th.obj ORDER BY vo.pos), false) AS flips
  FROM rel JOIN th ON th.pred_id = rel.pred_id AND th.obj = rel.obj JOIN vo ON vo.obj = th.obj AND vo.ver = th.ver),
asks2 AS (SELECT DISTINCT o.txn_id AS reader, o.pred_id, c.e FROM ops o JOIN com c ON c.txn_id = o.txn_id WHERE o.kind = 'pr'),
rp AS (SELECT a.reader, r.pred_id, r.obj, (SELECT max(v.pos) FROM vo v WHERE v.obj = r.obj AND (v.e < a.e OR v.e = a.e AND v.txn_id < a.reader)) AS pos FROM asks2 a JOIN rel r ON r.pred_id = a.pred_id),
fx AS (SELECT *, last_value(CASE WHEN flips THEN txn_id END IGNORE NULLS) OVER (PARTITION BY pred_id, obj ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto,
  first_value(CASE WHEN flips THEN txn_id END IGNORE NULLS) OVER (PARTITION BY pred_id, obj ORDER BY pos ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS nxt,
  first_value(txn_id) OVER (PARTITION BY pred_id, obj ORDER BY pos) AS fst FROM fl)"""


def _pred(name: str, run, select: str, reads: bool | str = True) -> None:
    _add(name, lambda spark, d: run(build.predicate_rows(spark, d, reads)), f"WITH {PRED}, {BASE}, {THETA}, {UNK}, {OPEN}, {CAND}, {FLIPS}\n{select}")


_pred("pred_ops", lambda h: h.ops.select("txn_id", "op_seq", "kind", "obj", "ver", "pred_id"), "SELECT txn_id, op_seq, kind, obj, ver, pred_id FROM ops")
_pred("theta_truth", prelim.theta_counts, "SELECT pred_id, count(*) AS versions, count(*) FILTER (holds) AS matching FROM th GROUP BY ALL", False)
_pred("theta_matches", dense.match_sums,
      "SELECT pred_id, count(*) AS matching, count(DISTINCT obj) AS objects, cast(sum(ver) AS bigint) AS total FROM th WHERE holds GROUP BY ALL", False)
_pred("theta_reads_expanded", prelim.theta_read_counts, "SELECT txn_id, pred_id, count(*) AS objects, count(ver) AS known FROM tr GROUP BY ALL", "packed")
_pred("unknown_theta_reads", prelim.unknown_theta_counts, "SELECT txn_id, pred_id, count(*) AS objects FROM tr WHERE ver IS NULL GROUP BY ALL", "packed")
_pred("open_theta_reads", lambda h: dense.unseen(h, by=("txn_id", "pred_id"), only=("reads",)).filter("reads > 0").select("txn_id", "pred_id", F.col("reads").alias("objects")), "SELECT reader AS txn_id, pred_id, count(*) AS objects FROM unk GROUP BY ALL", "packed")
_pred("pred_candidates", lambda h: dense.unseen(h, only=("candidates", "cand_sum")).filter("candidates > 0").select(F.col("txn_id").alias("reader"), "candidates", F.col("cand_sum").alias("total")), "SELECT reader, count(*) AS candidates, cast(sum(cand) AS bigint) AS total FROM fa GROUP BY ALL", "packed")
_pred("pred_undetermined", lambda h: dense.unseen(h, only=("edges", "edge_sum")).filter("edges > 0").select(F.col("txn_id").alias("reader"), "edges", F.col("edge_sum").alias("total")), "SELECT reader, count(*) AS edges, cast(sum(dst - cand) AS bigint) AS total FROM op GROUP BY ALL", "packed")
_pred("pred_wr", lambda h: dense.edge_sums(h).filter("wr > 0").select(F.col("txn_id").alias("dst"), F.col("wr").alias("edges"), F.col("wr_sum").alias("total")),
      "SELECT dst, count(*) AS edges, cast(sum(src) AS bigint) AS total FROM (SELECT DISTINCT coalesce(upto, fst) AS src, reader AS dst, fx.obj FROM rp JOIN fx ON fx.pred_id = rp.pred_id AND fx.obj = rp.obj AND fx.pos = rp.pos) WHERE src <> 0 AND src <> dst GROUP BY ALL", "asked")
_pred("pred_rw", lambda h: dense.edge_sums(h).filter("rw > 0").select(F.col("txn_id").alias("src"), F.col("rw").alias("edges"), F.col("rw_sum").alias("total")),
      "SELECT src, count(*) AS edges, cast(sum(dst) AS bigint) AS total FROM (SELECT DISTINCT reader AS src, nxt AS dst, fx.obj FROM rp JOIN fx ON fx.pred_id = rp.pred_id AND fx.obj = rp.obj AND fx.pos = rp.pos) WHERE dst IS NOT NULL AND src <> dst GROUP BY ALL", "asked")
_add("pred_avoided", lambda spark, d: _avoided(build.predicate_rows(spark, d, "packed")))
_pred("verdict_serial_predicates", verify.serializable, "SELECT true AS serializable", "packed")

# -- dependencies
ORDER = "vo AS (SELECT obj, ver, txn_id, row_number() OVER (PARTITION BY obj ORDER BY e, txn_id) AS pos FROM inst)"
edge = lambda df: df.select("src", "dst", "obj").distinct()


def _dep(name: str, run, select: str, history=(WR, _reg("wr"))) -> None:
    _add(name, lambda spark, d: run(history[1](spark, d)), f"WITH {history[0]}, {BASE}, {ORDER}\n{select}")


WR_SQL = "SELECT DISTINCT i.txn_id AS src, rd.txn_id AS dst, rd.obj FROM rd JOIN inst i ON i.obj = rd.obj AND i.ver = rd.ver WHERE i.txn_id <> rd.txn_id"
WW_SQL = "SELECT a.txn_id AS src, b.txn_id AS dst, a.obj FROM vo a JOIN vo b ON a.obj = b.obj AND b.pos {} WHERE a.txn_id <> b.txn_id"
AT = "(SELECT rd.txn_id, rd.obj, CASE WHEN rd.ver = 0 THEN 0 ELSE vo.pos END AS pos FROM rd LEFT JOIN vo ON vo.obj = rd.obj AND vo.ver = rd.ver) r"
RW_SQL = f"SELECT DISTINCT r.txn_id AS src, b.txn_id AS dst, r.obj FROM {AT} JOIN vo b ON b.obj = r.obj AND b.pos {{}} WHERE r.pos IS NOT NULL AND r.txn_id <> b.txn_id"
_dep("item_wr", lambda h: edge(deps.item_wr(h)), WR_SQL)
_dep("item_ww_direct", lambda h: edge(deps.item_ww(deps.version_order(h))), WW_SQL.format("= a.pos + 1"))
_dep("item_ww_all", lambda h: edge(deps.item_ww(deps.version_order(h), False)), WW_SQL.format("> a.pos"))
_dep("item_rw_direct", lambda h: edge(deps.item_rw(h, deps.version_order(h))), RW_SQL.format("= r.pos + 1"))
_dep("item_rw_all", lambda h: edge(deps.item_rw(h, deps.version_order(h), False)), RW_SQL.format("> r.pos"))
_dep("dsg_complete", lambda h: deps.dsg(h, deps.version_order(h)).groupBy("etype").agg(F.count("*").alias("n")),
     f"SELECT 'wr' AS etype, count(*) AS n FROM ({WR_SQL}) UNION ALL SELECT 'ww', count(*) FROM (SELECT DISTINCT * FROM ({WW_SQL.format('= a.pos + 1')})) UNION ALL SELECT 'rw', count(*) FROM ({RW_SQL.format('= r.pos + 1')})")
_dep("time_edges_full_count", deps.time_edge_count, "SELECT count(*) AS n FROM com a JOIN com b ON a.e <= b.s")
_dep("time_edges_reduced", deps.time_edges, """SELECT a.txn_id AS src, b.txn_id AS dst FROM com a JOIN com b ON b.s >= a.e
  JOIN LATERAL (SELECT min(c.e) AS bound FROM com c WHERE c.s >= a.e) x ON b.s < x.bound""")
_dep("ww_time_count", lambda h: _time_count(prelim.installed(h), prelim.installed(h)), "SELECT count(*) AS n FROM inst a JOIN inst b ON a.obj = b.obj AND a.e <= b.s")
_dep("rw_time_count", lambda h: _time_count(prelim.reads(h).select("txn_id", "obj", "s", "e").distinct(), prelim.installed(h)),
     "SELECT count(*) AS n FROM (SELECT DISTINCT txn_id, obj, s, e FROM rd) a JOIN inst b ON a.obj = b.obj AND a.e <= b.s")
FIRST = """SELECT DISTINCT r.txn_id AS src, w.txn_id AS dst, r.obj FROM (SELECT rd.txn_id, rd.obj, CASE WHEN rd.ver = 0 THEN -4611686018427387904 ELSE i.e END AS we FROM rd LEFT JOIN inst i ON i.obj = rd.obj AND i.ver = rd.ver
  WHERE rd.ver = 0 OR i.e IS NOT NULL) r JOIN inst w ON w.obj = r.obj AND w.s >= r.we JOIN LATERAL (SELECT min(x.e) AS bound FROM inst x WHERE x.obj = r.obj AND x.s >= r.we) b ON w.s < b.bound WHERE r.txn_id <> w.txn_id"""
_dep("rw_from_wr", lambda h: edge(deps.rw_from_wr(h)), FIRST)
_dep("known_graph_edges", lambda h: deps.known(h).groupBy("etype").agg(F.count("*").alias("n")), f"SELECT 'wr' AS etype, count(*) AS n FROM ({WR_SQL}) UNION ALL SELECT 'rw', count(*) FROM ({FIRST})")
_dep("time_contradictions", lambda h: edge(deps.time_contradictions(h, deps.item_wr(h))),
     f"SELECT x.* FROM ({WR_SQL}) x JOIN com a ON a.txn_id = x.src JOIN com b ON b.txn_id = x.dst WHERE b.e <= a.s", (RU, _reg("wr", "ru")))


def _time_count(a: DataFrame, b: DataFrame) -> DataFrame:
    """Pairs (a, b) of one object where a ended no later than b began: ends before each start, counted in one window an object."""
    from pyspark.sql import Window as W

    points = a.select("obj", F.col("e").alias("x"), F.lit(0).alias("k")).unionAll(b.select("obj", F.col("s").alias("x"), F.lit(1).alias("k")))
    n = F.sum(1 - F.col("k")).over(W.partitionBy("obj").orderBy("x", "k").rowsBetween(W.unboundedPreceding, 0))
    return points.withColumn("n", n).filter("k = 1").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


# -- constraints
PAIRS = "pr AS (SELECT a.obj, a.txn_id AS i, b.txn_id AS j FROM inst a JOIN inst b ON a.obj = b.obj AND a.txn_id < b.txn_id AND a.s < b.e AND b.s < a.e)"
SETS = """st AS (SELECT obj, i, j, 0 AS side, i AS src, j AS dst FROM pr UNION ALL SELECT obj, i, j, 1, j, i FROM pr
  UNION SELECT pr.obj, i, j, 0, rd.txn_id, j FROM pr JOIN inst w ON w.obj = pr.obj AND w.txn_id = pr.i JOIN rd ON rd.obj = w.obj AND rd.ver = w.ver WHERE rd.txn_id <> j
  UNION SELECT pr.obj, i, j, 1, rd.txn_id, i FROM pr JOIN inst w ON w.obj = pr.obj AND w.txn_id = pr.j JOIN rd ON rd.obj = w.obj AND rd.ver = w.ver WHERE rd.txn_id <> i)"""


def _con(name: str, run, select: str, mix: str = "wr") -> None:
    _add(name, lambda spark, d: run(build.registers(spark, d, mix)), f"WITH {texts.registers('duckdb', mix)}, {BASE}, {PAIRS}, {SETS}\n{select}")


_con("item_pairs_total", lambda h: cs.item_pair_counts(h).agg(F.sum("pairs").alias("pairs")), "SELECT count(*) AS pairs FROM inst a JOIN inst b ON a.obj = b.obj AND a.txn_id < b.txn_id")
_con("item_pairs_overlap", cs.item_pairs, "SELECT obj, i, j FROM pr")
_con("item_edge_sets", lambda h: cs.item_edge_sets(h, cs.item_pairs(h)), "SELECT obj, i, j, side, src, dst FROM st")
_con("item_coalesced", lambda h: cs.coalesced(cs.item_edge_sets(h, cs.item_pairs(h))), "SELECT DISTINCT concat_ws('-', i, j) AS cid, i, j, side, src, dst FROM st")
_con("search_space_log2", lambda h: cs.search_space(cs.item_pairs(h)), "SELECT count(*) AS log2_assignments FROM (SELECT DISTINCT i, j FROM pr)", "wh")
for m in ("rh", "wh"):
    _con(f"item_pairs_overlap_{m}", lambda h: cs.item_pairs(h).agg(F.count("*").alias("pairs")), "SELECT count(*) AS pairs FROM pr", m)

# -- bands and islands
IX = "ix AS (SELECT *, row_number() OVER (ORDER BY s, txn_id) - 1 AS idx FROM com)"
BND = f"""{IX}, bd AS (SELECT a.txn_id, a.idx, (SELECT count(*) FROM ix b WHERE b.s < a.e) - 1 AS r, (SELECT min(b.idx) FROM ix b WHERE b.e > a.s) AS l FROM ix a)"""


def _band(name: str, run, select: str) -> None:
    _add(name, lambda spark, d: run(build.registers(spark, d, "wr")), f"WITH {WR}, {BASE}, {PAIRS}, {SETS}, {BND}\n{select}")


_band("overlap_bounds", lambda h: bounds(h).select("txn_id", "idx", "l", "r"), "SELECT txn_id, idx, l, r FROM bd")
_band("compact_layout", lambda h: layout(bounds(h)).select("idx", "l", "r", "off"), "SELECT idx, l, r, cast(sum(r - l + 1) OVER (ORDER BY idx) - (r - l + 1) AS bigint) AS off FROM bd")
_band("compact_cells_vs_full", lambda h: bounds(h).agg(F.sum(F.col("r") - F.col("l") + 1).alias("cells"), (F.count("*") * F.count("*")).alias("full_cells")), "SELECT cast(sum(r - l + 1) AS bigint) AS cells, count(*) * count(*) AS full_cells FROM bd")
_band("overlap_degree_stats", lambda h: bounds(h).select((F.col("r") - F.col("l")).alias("d")).agg(F.min("d").alias("least"), F.max("d").alias("most"), F.sum("d").alias("total")), "SELECT min(r - l) AS least, max(r - l) AS most, cast(sum(r - l) AS bigint) AS total FROM bd")
_band("quiescent_epochs", lambda h: islands.epochs(bounds(h)).groupBy("epoch").agg(F.count("*").alias("n")),
      "SELECT epoch, count(*) AS n FROM (SELECT max(CASE WHEN NOT EXISTS (SELECT 1 FROM bd p WHERE p.idx < bd.idx AND p.r >= bd.idx) THEN idx END) OVER (ORDER BY idx) AS epoch FROM bd) GROUP BY ALL")

# -- verdicts
verdict = verify.verdict
for m in ("rh", "wr", "wh"):
    _con(f"verdict_serial_{m}", verdict, "SELECT true AS serializable, cast(NULL AS varchar) AS reason, count(*) AS constraints FROM (SELECT DISTINCT i, j FROM pr)", m)
_add("verdict_read_uncommitted", lambda spark, d: verify.verdict(build.registers(spark, d, "wr", "ru")).select("serializable", "reason"), "SELECT false AS serializable, 'aborted_read' AS reason")
_add("verdict_serial_orders", lambda spark, d: verify.verdict(build.orders_mix(spark, d)).select("serializable"), "SELECT true AS serializable")
_add("verdict_serial_social", lambda spark, d: verify.verdict(build.social(spark, d)).select("serializable"), "SELECT true AS serializable")
_add("worked_example_complete", lambda spark, d: small.run(fixtures.get(spark, "worked_example")[0], _complete).drop("case_no"), "SELECT 'complete' AS measure, 72 AS value UNION ALL SELECT 'serializable', 0")
_add("worked_example_verdicts", lambda spark, d: _verdicts(spark, ["worked_example"]), "SELECT 'worked_example' AS name, false AS timed, false AS two_stage, false AS serial_orders, true AS frontier, 'accept' AS without_predicates")
_add("detection", lambda spark, d: measures.detection(spark))
_add("detection_timed", lambda spark, d: measures.detection(spark).select("name", "class", "timed"), measures.TIMED_SQL)
_add("detection_cube", lambda spark, d: measures.detection_cube(spark))
_add("detection_rate_pivot", lambda spark, d: measures.detection_pivot(spark))
_add("false_alarms", lambda spark, d: measures.detection(spark, fixtures.twin).agg(F.count("*").alias("histories"), F.count_if("timed").alias("rejected")), "SELECT 36 AS histories, 0 AS rejected")
_add("verdict_small_bruteforce", lambda spark, d: cases.agreement(spark).select("cases", "wrong"), "SELECT 2000 AS cases, 0 AS wrong")

# -- baselines
UPD = """(SELECT a.obj, a.txn_id AS i, b.txn_id AS j FROM up a JOIN up b ON a.obj = b.obj AND a.txn_id < b.txn_id AND a.op_s < b.e AND b.op_s < a.e)"""
UP = "up AS (SELECT w.txn_id, w.obj, w.op_s, c.e FROM (SELECT txn_id, obj, arg_max(op_s, op_seq) AS op_s FROM ops WHERE kind = 'w' GROUP BY ALL) w JOIN com c USING (txn_id))"
for label, run, sql in (
    ("protocol_overlapping_writes", protocol.overlapping_updates, f"SELECT obj, i, j FROM {UPD}"),
    ("protocol_verdict", protocol.verify, f"SELECT CASE WHEN count(*) > 0 THEN 'reject' ELSE 'accept' END AS verdict, count(*) AS flagged FROM {UPD}"),
):
    _add(label, lambda spark, d, run=run: run(build.registers(spark, d, "wr")), f"WITH {WR}, {BASE}, {UP}\n{sql}")
_add("protocol_abstains", lambda spark, d: protocol.verify(_untimed_writes(build.registers(spark, d, "wr"))).select("verdict"), "SELECT 'abstain' AS verdict")
_add("polygraph_verdict_small", lambda spark, d: polygraph.verdict(build.registers(spark, d, "wr")), "SELECT true AS serializable")

_add("verdict_by_protocol", lambda spark, d: schedulers.verdicts(spark).filter("protocol <> 'snapshot'"),
     "SELECT * FROM (VALUES ('two_phase_locking', 300, 0), ('optimistic', 300, 0), ('timestamp_ordering', 300, 0), ('serializable_snapshot', 300, 0)) t(protocol, runs, rejected)")

# -- complete histories
_add("history_differences", lambda spark, d: complete.differences(build.registers(spark, d, "wr"), build.registers(spark, d, "wr", "snapshot")).select("txn_id", "op_seq", "obj"),
     "SELECT a.txn_id, a.op_seq, a.obj FROM (WITH {} SELECT * FROM ops) a JOIN (WITH {} SELECT * FROM ops) b ON a.txn_id = b.txn_id AND a.op_seq = b.op_seq AND a.obj = b.obj AND a.kind = b.kind WHERE a.ver <> b.ver".format(WR, texts.registers("duckdb", "wr", "snapshot")))
_add("complete_is_serializable", lambda spark, d: _complete_verdict(build.registers(spark, d, "wr")), "SELECT true AS serializable, 0 AS bad_reads, 0 AS cyclic")
_add("complete_with_predicates", lambda spark, d: _complete_verdict(build.predicate_rows(spark, d, "packed")), "SELECT true AS serializable, 0 AS bad_reads, 0 AS cyclic")
_add("verdict_by_isolation", lambda spark, d: _by_isolation(spark, d))
_con("compatible_graph", lambda h: _chosen(h), """SELECT DISTINCT st.src, st.dst FROM st JOIN com a ON a.txn_id = st.i JOIN com b ON b.txn_id = st.j
  WHERE st.side = CASE WHEN a.e < b.e OR a.e = b.e AND a.txn_id < b.txn_id THEN 0 ELSE 1 END""")
_pred("validation_constraints", lambda h: dense.unseen(h, "validations").select(F.col("txn_id").alias("reader"), "options", "before", "after"),
      """SELECT u.reader, count(*) AS options, cast(sum(coalesce(upto, fst)) AS bigint) AS before, cast(coalesce(sum(nxt), 0) AS bigint) AS after FROM unk u
  JOIN fx ON fx.pred_id = u.pred_id AND fx.obj = u.obj JOIN vo ON vo.obj = fx.obj AND vo.pos = fx.pos JOIN th ON th.pred_id = u.pred_id AND th.obj = vo.obj AND th.ver = vo.ver WHERE NOT th.holds AND fx.txn_id <> u.reader GROUP BY ALL""", "packed")

# -- injected anomalies
for kind in ("stale_read", "lost_update", "write_skew", "aborted_read"):
    for k in (1, 3):
        _add(f"verdict_injected_{kind}_{k}", lambda spark, d, kind=kind, k=k: verify.timed(inject.apply(build.registers(spark, d, "wr"), kind, k)).select("serializable"), "SELECT false AS serializable")
_add("injected_operations", lambda spark, d: _injected(build.registers(spark, d, "wr")), "SELECT 'lost_update' AS kind, 12 AS changed UNION ALL SELECT 'write_skew', 18 UNION ALL SELECT 'stale_read', 3")

# -- witnesses
_con("witness_replays", lambda h: _replayed(h), "SELECT (SELECT count(*) FROM com) AS txns, (SELECT count(*) FROM ops o JOIN com c USING (txn_id) WHERE o.kind <> 'w') AS reads, 0 AS wrong")
_add("witness_cycles", lambda spark, d: verify.witness_cycles(inject.write_skew(build.registers(spark, d, "wr"), 2)).groupBy("reason", "kind").agg(F.count("*").alias("edges")))

# -- measures
FIVE = [(m, texts.registers("duckdb", m)) for m in ("wh", "wr", "rh")] + [("social", texts.social("duckdb")), ("orders", texts.orders_mix("duckdb"))]


def _five(stages: dict[str, str]) -> str:
    """One SELECT a workload and stage, each with its history."""
    return " UNION ALL ".join(
        f"SELECT * FROM (WITH {ctes}, {BASE} SELECT '{name}' AS workload, {', '.join(f'({sql}) AS {stage}' for stage, sql in stages.items())})" for name, ctes in FIVE
    )


TOTAL_SQL = "SELECT cast(coalesce(sum(w * (w - 1) / 2), 0) AS bigint) FROM (SELECT count(DISTINCT txn_id) AS w FROM inst GROUP BY obj)"
OPEN_SQL = "SELECT count(*) FROM inst a JOIN inst b ON a.obj = b.obj AND a.txn_id < b.txn_id AND a.s < b.e AND b.s < a.e"
COUNTS_SQL = _five({"total": TOTAL_SQL, "overlapping": OPEN_SQL})
_add("constraint_counts", measures.constraint_counts, COUNTS_SQL)
_add("constraint_reduction", measures.constraint_reduction)
_add("constraint_reduction_rollup", measures.constraint_rollup,
     f"WITH c AS ({COUNTS_SQL}), l AS (SELECT workload, 'total' AS stage, total AS n FROM c UNION ALL SELECT workload, 'overlapping', overlapping FROM c) SELECT coalesce(workload, 'all') AS workload, stage, cast(sum(n) AS bigint) AS n FROM l GROUP BY GROUPING SETS ((workload, stage), (stage))")
_add("closure_costs", lambda spark, d: measures.closure_costs(build.registers(spark, d, "wr")))
#: All pairs in the closure, by a recursion along read edges, first-wave time edges and edges that these settle.
CLOSURE_SQL = f"""WITH RECURSIVE {WR}, {BASE}, wre AS ({WR_SQL}), rwe AS ({FIRST}),
te AS (SELECT a.txn_id AS src, b.txn_id AS dst FROM com a JOIN (SELECT x.txn_id, (SELECT min(c.e) FROM com c WHERE c.s >= x.e) AS bound FROM com x) m ON m.txn_id = a.txn_id JOIN com b ON b.s >= a.e AND b.s < m.bound),
ed AS (SELECT src, dst FROM te UNION SELECT src, dst FROM wre UNION SELECT src, dst FROM rwe),
cl AS (SELECT src, dst FROM ed UNION SELECT cl.src, ed.dst FROM cl JOIN ed ON ed.src = cl.dst)
SELECT (SELECT count(*) FROM cl) AS pairs, (SELECT count(*) FROM com) AS txns"""
_add("compact_closure_pairs", lambda spark, d: _closure_pairs(build.registers(spark, d, "wr")), CLOSURE_SQL)
_add("closure_update_costs", lambda spark, d: measures.update_costs(build.registers(spark, d, "wr")))
_add("solver_costs", lambda spark, d: measures.solver_costs(build.registers(spark, d, "wr")))
_con("cnf_sizes", lambda h: encodings.sizes(h), """SELECT 'reduced_items' AS encoding, count(*) AS variables, 0 AS clauses, 0 AS literals FROM (SELECT DISTINCT i, j FROM pr)
UNION ALL SELECT 'edge_variables', 2 * p + e, 2 * p + 2 * p + n, 3 * n + 2 * p + 4 * p FROM
  (SELECT (SELECT count(*) FROM (SELECT DISTINCT i, j FROM pr)) AS p, (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM st)) AS e, (SELECT count(*) FROM (SELECT DISTINCT i, j, side, src, dst FROM st)) AS n)
UNION ALL SELECT enc, 2 * p + e + t * (t - 1), 4 * p + n + t * (t - 1) + c * t * (t - 1) * (t - 2), 3 * n + 6 * p + 2 * t * (t - 1) + 3 * c * t * (t - 1) * (t - 2) FROM
  (SELECT (SELECT count(*) FROM (SELECT DISTINCT i, j FROM pr)) AS p, (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM st)) AS e, (SELECT count(*) FROM (SELECT DISTINCT i, j, side, src, dst FROM st)) AS n,
   (SELECT count(*) FROM (SELECT src AS t FROM st UNION SELECT dst FROM st)) AS t), (VALUES ('plain', 1), ('plain_without_transitivity', 0)) v(enc, c)""")
_add("cnf_sizes_predicates", lambda spark, d: encodings.reduced_predicate_sums(build.predicate_rows(spark, d, "packed")),
     f"""WITH {PRED}, {BASE}, {THETA}, {UNK}, {OPEN}, {CAND}, k AS (SELECT reader, pred_id, obj, count(*) AS k FROM fa GROUP BY ALL),
o AS (SELECT f.reader, f.pred_id, f.obj, count(*) AS n FROM fa f JOIN wr w ON w.obj = f.obj AND w.pred_id = f.pred_id AND w.holds WHERE w.txn_id <> f.cand AND w.txn_id <> 0 AND w.txn_id <> f.reader GROUP BY ALL)
SELECT 'reduced_predicates' AS encoding, cast(sum(k + coalesce(n, 0)) AS bigint) AS variables, cast(sum(1 + k * (k - 1) / 2 + coalesce(n, 0)) AS bigint) AS clauses, cast(sum(k + k * (k - 1) + 3 * coalesce(n, 0)) AS bigint) AS literals
FROM k LEFT JOIN o USING (reader, pred_id, obj)""")
_add("scaling_counts", lambda spark, d: measures.prefixes(build.orders_mix(spark, d)),
     f"""WITH {texts.orders_mix("duckdb")}, {BASE}, p AS (SELECT txn_id, least(10, (row_number() OVER (ORDER BY s, txn_id) - 1) * 10 // (SELECT count(*) FROM com) + 1) AS step FROM com),
q AS (SELECT greatest(x.step, y.step) AS step FROM inst a JOIN inst b ON a.obj = b.obj AND a.txn_id < b.txn_id AND a.s < b.e AND b.s < a.e JOIN p x ON x.txn_id = a.txn_id JOIN p y ON y.txn_id = b.txn_id)
SELECT k.step, (SELECT count(*) FROM p WHERE p.step <= k.step) AS txns, (SELECT count(*) FROM q WHERE q.step <= k.step) AS pairs FROM (SELECT DISTINCT step FROM p) k""")
_add("pruned_item_counts", lambda spark, d: verify.timed(build.registers(spark, d, "wh")).select("constraints", "residual"))
_add("scaling", lambda spark, d: measures.scaling(spark, build.orders_mix(spark, d), [0.1, 0.5, 1.0]))

# -- streams
_add("stream_window_reads", live.window_reads, live.WINDOW_SQL)
_add("stream_sliding_windows", live.sliding_counts, live.SLIDING_SQL)
_add("stream_session_windows", live.sessions, live.SESSION_SQL)
_add("stream_dedup", live.dedup, "SELECT count(*) AS n FROM events")
_add("stream_wr_edges", lambda spark, d: live.wr_edges(spark, build.registers(spark, d, "wr")), f"WITH {WR}, {BASE}\n{WR_SQL}")
_add("stream_object_state", lambda spark, d: live.object_versions(spark, build.registers(spark, d, "wr")),
     f"WITH {WR}, {BASE} SELECT obj, count(*) FILTER (o.kind = 'w') AS writes, count(*) FILTER (o.kind <> 'w') AS readers FROM ops o JOIN com USING (txn_id) GROUP BY ALL")
_add("stream_static_predicates", lambda spark, d: live.matched_predicates(spark, build.predicate_rows(spark, d, "packed")), f"WITH {PRED} SELECT pred_id, count(*) AS n FROM ops WHERE kind = 'pr' AND ver IS NOT NULL GROUP BY ALL")
_add("stream_verdicts_equal_batch", lambda spark, d: live.online(spark, build.registers(spark, d, "wr")), f"WITH {WR}, {BASE} SELECT true AS serializable, false AS provisional, count(*) AS decided FROM com")


def _untimed_writes(h):
    """h as a log that gives times of reads only."""
    return h.but(ops=h.ops.withColumn("op_s", F.when(F.col("kind") != "w", F.col("op_s"))))


def _complete_verdict(h) -> DataFrame:
    """The history completed in the order of ends. Where that order explains every read, all edges point forward in it and need not be made."""
    if verify.explained(h):
        return h.txns.sparkSession.sql("SELECT true AS serializable, 0L AS bad_reads, 0L AS cyclic")
    h = dense.unpacked(h)
    return complete.is_serializable(h, deps.version_order(h), deps.serial_theta_reads(h) if h.preds is not None else None).select("serializable", "bad_reads", "cyclic")


def _by_isolation(spark: SparkSession, d: str) -> DataFrame:
    """(level, serializable, verdict): the register history under each simulated level, by the test for complete histories with the order
    of ends as version order, and by the verifier, which knows no version order."""
    rows = []
    for level in ("serial", "snapshot", "rc", "ru"):
        with scope(spark):
            h = build.registers(spark, d, "wr", level)
            h = h.but(txns=written(h.txns), ops=written(h.ops))
            if verify.explained(h):
                rows.append((level, True, True))
            elif prelim.findings(h).limit(1).count():  # bad reads refute a history either way
                rows.append((level, False, False))
            else:
                told = verify.told_by_graph(h, written(verify.known_edges(h, True)))
                # what told accepts has no cycle in the complete graph, time edges included
                by_ends = bool(told) or complete.is_serializable(h, deps.version_order(h)).head().serializable
                rows.append((level, by_ends, verify.verdict(h, graph=False).head().serializable if told is None else told))
    return spark.createDataFrame(rows, "level string, serializable boolean, verdict boolean")


def _chosen(h) -> DataFrame:
    sets = cs.coalesced(cs.item_edge_sets(h, cs.item_pairs(h)))
    return complete.chosen_graph(sets, complete.by_end(sets, h))


def _injected(h) -> DataFrame:
    """Operations that three injections of each kind changed."""
    out = None
    for kind in ("lost_update", "write_skew", "stale_read"):
        row = inject.changed(h, inject.apply(h, kind, 3)).agg(F.count("*").alias("changed")).select(F.lit(kind).alias("kind"), "changed")
        out = row if out is None else out.unionAll(row)
    return out


def _replayed(h) -> DataFrame:
    order = verify.witness(h)
    reads = verify.replay(h, order).agg(F.count("*").alias("reads"), F.count_if(F.col("ver") != F.col("sees")).alias("wrong"))
    return order.agg(F.count("*").alias("txns")).withColumn("one", F.lit(1)).join(reads.withColumn("one", F.lit(1)), "one").drop("one")


def _closure_pairs(h) -> DataFrame:
    got = measures.closure_costs(h, ["timed_purdom"])
    return got.select("pairs").withColumn("one", F.lit(1)).join(prelim.committed(h).agg(F.count("*").alias("txns")).withColumn("one", F.lit(1)), "one").drop("one")


def _avoided(h) -> DataFrame:
    """What client times leave of the predicate constraints."""
    return cs.avoided(h, cs.predicate(h, cs.unmet(h))).select("reader", "obj", "cand", "src", "dst", "via_src", "via_dst")


def _complete(txns: list[dict], holds: dict) -> dict:
    total, good = small.exhaustive(txns, holds)
    return {"complete": total, "serializable": good}


def _verdicts(spark: SparkSession, names: list[str]) -> DataFrame:
    rows = []
    for n in names:
        h, _ = fixtures.get(spark, n)
        got = small.run(h, lambda t, x: {"two_stage": small.two_stage(t, x), "serial_orders": bool(small.serial_orders(t, x)), "frontier": small.frontier(t)}).collect()
        by = {r.measure: bool(r.value) for r in got}
        without = verify.timed(h, predicates=False).head().serializable
        rows.append((n, verify.timed(h).head().serializable, by["two_stage"], by["serial_orders"], by["frontier"], "accept" if without else "reject"))
    return spark.createDataFrame(rows, "name string, timed boolean, two_stage boolean, serial_orders boolean, frontier boolean, without_predicates string")
