"""Sizes of the formulas that encode a history's constraints: variables, clauses and literals, counted without making the formulas."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderproof.operators import constraints as cs
from orderproof.operators import dense, prelim
from orderproof.schema import History


def _row(df: DataFrame, name: str, variables, clauses, literals) -> DataFrame:
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return df.agg(zero(variables).alias("variables"), zero(clauses).alias("clauses"), zero(literals).alias("literals")).withColumn("encoding", F.lit(name)).select("encoding", "variables", "clauses", "literals")


def _beside(a: DataFrame, b: DataFrame) -> DataFrame:
    """Two tables of one row as one row."""
    return a.withColumn("one", F.lit(1)).join(b.withColumn("one", F.lit(1)), "one").drop("one")


def reduced_items(sets: DataFrame) -> DataFrame:
    """One variable a constraint, whose sign chooses the side: no clause is needed."""
    return _row(sets.select("cid").distinct(), "reduced_items", F.count("*"), F.lit(0), F.lit(0))


def reduced_predicates(rows: DataFrame) -> DataFrame:
    """rows as constraints.predicate() gives them. A variable a candidate and one an open edge; one clause that some candidate holds,
    one for each two that not both do, and one of three literals that an open edge holds if its candidate and its write order do."""
    each = rows.groupBy("cid").agg(F.countDistinct("cand").alias("k"), F.count(F.when(F.col("via_src").isNotNull(), 1)).alias("open"))
    twice = F.col("k") * (F.col("k") - 1)
    return _row(each, "reduced_predicates", F.sum(F.col("k") + F.col("open")), F.sum(1 + twice / 2 + F.col("open")), F.sum(F.col("k") + twice + 3 * F.col("open")))


def reduced_predicate_sums(h: History) -> DataFrame:
    """reduced_predicates() of constraints.predicate(h), counted without making its rows."""
    each = dense.unseen(h, by=())
    k, twice, open_ = F.sum("candidates"), F.sum("twice"), F.sum("edges")
    return _row(each, "reduced_predicates", k + open_, F.sum("cids") + twice / 2 + open_, k + twice + 3 * open_)


def edge_variables(sets: DataFrame) -> DataFrame:
    """A variable an edge and two a constraint, one for each side's edges together; a clause that a side holds, one that not both do, and
    for a side's variable and its edges a clause an edge and one for all: the exclusive or of two conjunctions."""
    sides = sets.groupBy("cid", "side").agg(F.countDistinct("src", "dst").alias("edges"))
    own = _row(sides, "edge_variables", F.count("*"), F.sum(F.col("edges") + 1) + F.count("*"), F.sum(2 * F.col("edges") + F.col("edges") + 1) + 2 * F.count("*"))
    edges = sets.select("src", "dst").distinct().agg(F.count("*").alias("more"))
    return _beside(own, edges).select("encoding", (F.col("variables") + F.col("more")).alias("variables"), "clauses", "literals")


def plain(sets: DataFrame, transitive: bool = True) -> DataFrame:
    """Edge variables as above, with two variables for each two transactions that meet in a constraint and an exclusive or of these
    (two clauses of two literals); with `transitive` also a clause of three for each three transactions in an order, which acyclicity
    needs."""
    met = edge_variables(sets)
    n = sets.select(F.explode(F.array("src", "dst")).alias("t")).agg(F.countDistinct("t").alias("n"))
    m = F.col("n").cast("double")
    pairs, triples = m * (m - 1) / 2, m * (m - 1) * (m - 2)
    more = triples if transitive else F.lit(0.0)
    return _beside(met, n).select(
        F.lit("plain" if transitive else "plain_without_transitivity").alias("encoding"), (F.col("variables") + 2 * pairs).cast("long").alias("variables"),
        (F.col("clauses") + 2 * pairs + more).cast("long").alias("clauses"), (F.col("literals") + 4 * pairs + 3 * more).cast("long").alias("literals"),
    )


def sizes(h: History, timed: bool = True) -> DataFrame:
    """(encoding, variables, clauses, literals) for the item constraints of a history, and for its predicate constraints if it has any."""
    sets = cs.coalesced(cs.item_edge_sets(h, cs.item_pairs(h, timed)))
    out = reduced_items(sets).unionAll(edge_variables(sets)).unionAll(plain(sets, False)).unionAll(plain(sets))
    if h.preds is not None:
        out = out.unionAll(reduced_predicates(cs.predicate(h, cs.unmet(h) if timed else prelim.open_theta_reads(h))))
    return out
