"""Schemas of a transaction history, and the bundle of tables that is one."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

TXNS = "txn_id long, session_id int, session_pos int, status string, s long, e long, ttype string"
OPS = "txn_id long, op_seq int, kind string, obj string, ver long, pred_id int, op_s long, op_e long"
VERS = "obj string, ver long, txn_id long, v1 double, v2 double, deleted boolean"
PREDS = "pred_id int, domain string, col string, lo double, hi double"
EDGES = "src long, dst long, etype string, obj string, pred_id int"
#: The implicit transaction that wrote version 0 of every object before all others.
INITIAL = 0


@dataclass(frozen=True)
class Made:
    """Rows of History.returned as they are made, for what reads them object by object: rows(value) gives (ver, txns, preds) of the value
    `held` of a row of held (obj, held), a row an object. So they lie on no disk and go through no exchange."""

    held: DataFrame
    rows: Callable


@dataclass(frozen=True)
class History:
    """Observed history. Times are microseconds with s < e; status is c (committed) or a (aborted); kinds are r, w and pr
    (predicate read: ver is null where the version it skipped is unknown). returned: (obj, ver, txns, preds), what predicate reads returned of
    objects that ops don't tell, packed as 64- and 32-bit numbers; only operators/dense.py reads it. made: the same rows, see Made, as
    long as returned isn't replaced."""

    txns: DataFrame
    ops: DataFrame
    vers: DataFrame | None = None
    preds: DataFrame | None = None
    returned: DataFrame | None = None
    made: Made | None = None

    def but(self, **tables) -> History:
        if "returned" in tables:
            tables.setdefault("made", None)
        return replace(self, **tables)
