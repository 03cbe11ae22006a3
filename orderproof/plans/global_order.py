"""Global ranks and running values without a one-task window: slices of the order are numbered on their own, then offset.

Slices are cut at quantiles of the order, so they hold about equally many rows however the values lie (rows of one value stay
together), and there are `slices` of them at most. With keys each key's rows are cut at the same places: a hot key is as many tasks
as any key can have slices.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SLICES = 256


def sliced(df: DataFrame, at: str, slices: int = SLICES) -> DataFrame:
    """df with __slice: how many of the quantiles of `at` lie at or below it."""
    cuts = df.agg(F.percentile_approx(at, [k / slices for k in range(1, slices)], 10_000)).head()[0] or []
    cuts = sorted(set(cuts))
    if not cuts:
        return df.withColumn("__slice", F.lit(0))
    size = 1 << len(cuts).bit_length()
    known = F.lit([*cuts, *[(1 << 63) - 1] * (size - len(cuts))])
    steps = F.lit([size >> k for k in range(1, size.bit_length())])
    below = lambda p, step: F.get(known, p + step - 1)
    return df.withColumn("__slice", F.aggregate(steps, F.lit(0), lambda p, step: F.when(below(p, step) <= F.col(at), p + step).otherwise(p)))


def running_all(df: DataFrame, at: str, ties: list[str], wanted: dict[str, tuple[str, Column, bool]], keys: list[str] = ()) -> DataFrame:
    """df with running values, each from (sum, min or max; value; forward or backward) in the order of (at, *ties) within the keys,
    a row's own value included. Sums begin at 0; nulls don't count."""
    how = {"sum": F.sum, "max": F.max, "min": F.min}
    both = {"sum": lambda a, b: F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0)), "max": F.greatest, "min": F.least}
    keys = list(keys)
    cut = sliced(df.withColumns({f"__v_{n}": v for n, (_, v, _) in wanted.items()}), at)
    total = cut.groupBy(*keys, "__slice").agg(*(how[h](f"__v_{n}").alias(f"__t_{n}") for n, (h, _, _) in wanted.items()))
    over = W.partitionBy(*keys).orderBy("__slice")
    side = {True: over.rowsBetween(W.unboundedPreceding, -1), False: over.rowsBetween(1, W.unboundedFollowing)}
    beside = total.select(*keys, "__slice", *(how[h](f"__t_{n}").over(side[f]).alias(f"__b_{n}") for n, (h, _, f) in wanted.items()))
    within = W.partitionBy(*keys, "__slice").orderBy(at, *ties)
    frame = {True: within.rowsBetween(W.unboundedPreceding, 0), False: within.rowsBetween(0, W.unboundedFollowing)}
    own = cut.withColumns({f"__o_{n}": how[h](f"__v_{n}").over(frame[f]) for n, (h, _, f) in wanted.items()})
    met = own.join(beside if keys else F.broadcast(beside), [*keys, "__slice"])  # without keys a row a slice
    out = met.withColumns({n: both[h](F.col(f"__b_{n}"), F.col(f"__o_{n}")) for n, (h, _, _) in wanted.items()})
    return out.drop("__slice", *(f"__{x}_{n}" for x in "vbo" for n in wanted))


def running(df: DataFrame, at: str, ties: list[str], value: Column, how: str, name: str, keys: list[str] = ()) -> DataFrame:
    """df with the running sum, min or max of `value` in the order of (at, *ties) within the keys."""
    return running_all(df, at, ties, {name: (how, value, True)}, keys)


def ranked(df: DataFrame, at: str, ties: list[str], name: str = "idx", keys: list[str] = ()) -> DataFrame:
    """df with its place, from 0, in the order of (at, *ties) within the keys."""
    return running(df, at, ties, F.lit(1), "sum", name, keys).withColumn(name, (F.col(name) - 1).cast("long"))
