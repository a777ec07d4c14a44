"""Joins with a gate: drop what certainly has no partner, then join exactly.

The gate sits on the scan of the large side, below any exchange, so only survivors are
shuffled. It has no false negatives; the exact join behind it keeps answers equal to
those of the plain join.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from sieve.operators import probe
from sieve.operators.build import Filter, build
from sieve.plans.names import fresh

#: What a gate on the left side may do: drop its sure non-members, or only route them.
LEGAL = {"inner": "drop", "left_semi": "drop", "right_outer": "drop", "left_outer": "route", "left_anti": "route", "full_outer": "route"}


def legal_prefilter(how: str) -> str:
    """drop or route; raises for joins that have no key to gate on."""
    if how not in LEGAL:
        raise ValueError(f"no gate for {how} joins")
    return LEGAL[how]


def _pairs(on: str | tuple[str, str] | list[tuple[str, str]]) -> list[tuple[str, str]]:
    if isinstance(on, str):
        return [(on, on)]
    return [on] if isinstance(on, tuple) else list(on)


def _test(pairs: list[tuple[str, str]]) -> Column:
    out = F.lit(True)
    for a, b in pairs:
        out = out & (F.col(f"l.`{a}`") == F.col(f"r.`{b}`"))
    return out


def gated(fact: DataFrame, dim: DataFrame, on, how: str = "inner", kind: str = "fuse3", f: Filter | None = None, plan: str | None = None, **built) -> DataFrame:
    """``fact`` joined to ``dim`` with a gate on ``fact``; rows and columns as the plain join's."""
    pairs = _pairs(on)
    left, right = [a for a, _ in pairs], [b for _, b in pairs]
    f = f or build(dim, right, kind, **built)
    r = dim.alias("r")
    if legal_prefilter(how) == "drop":
        return probe.semi(fact, f, left, plan).alias("l").join(r, _test(pairs), how)
    [flag] = fresh(fact.columns, "maybe")
    flagged = probe.contains(fact, f, left, flag, plan)
    maybe, sure = flagged.filter(F.col(flag)).drop(flag), flagged.filter(~F.col(flag)).drop(flag)
    if how == "left_anti":
        return maybe.alias("l").join(r, _test(pairs), "left_anti").unionByName(sure)
    joined = maybe.alias("l").join(r, _test(pairs), how)
    padding = sure.select("*", *[F.lit(None).cast(x.dataType).alias(x.name) for x in dim.schema])
    return joined.union(padding)


def semi(fact: DataFrame, dim: DataFrame, on, kind: str = "fuse3", **how) -> DataFrame:
    """Rows of ``fact`` that have a partner in ``dim``."""
    return gated(fact, dim, on, "left_semi", kind, **how)


def anti(fact: DataFrame, dim: DataFrame, on, kind: str = "fuse3", **how) -> DataFrame:
    """Rows of ``fact`` that have none; sure non-members skip the lookup."""
    return gated(fact, dim, on, "left_anti", kind, **how)


def exact_semi(fact: DataFrame, dim: DataFrame, on) -> DataFrame:
    """The ungated join: the ground truth and the baseline."""
    pairs = _pairs(on)
    return fact.alias("l").join(dim.alias("r"), _test(pairs), "left_semi")


def star(fact: DataFrame, dims: list[tuple[DataFrame, tuple[str, str]]], kind: str = "fuse3", pass_rates: list[float] | None = None, **how) -> DataFrame:
    """Gates of all dimensions first, the most selective before the others, then exact semi joins."""
    gates = [(build(d, b, kind, **how), a) for d, (a, b) in dims]
    out = probe.all_of(fact, gates, pass_rates)
    for d, on in dims:
        out = exact_semi(out, d, on)
    return out


def range_join(left: DataFrame, right: DataFrame, key: tuple[str, str], at: str, start: str, end: str) -> DataFrame:
    """Rows of both sides with equal keys and ``at`` in [start, end)."""
    return left.alias("l").join(right.alias("r"), (F.col(f"l.`{key[0]}`") == F.col(f"r.`{key[1]}`")) & (F.col(f"l.`{at}`") >= F.col(f"r.`{start}`")) & (F.col(f"l.`{at}`") < F.col(f"r.`{end}`")))


def asof_join(left: DataFrame, right: DataFrame, key: tuple[str, str], at: tuple[str, str], value: str, out: str) -> DataFrame:
    """``left`` with ``right``'s last value at or before each row's time, by key.

    One union and one window: no row meets all rows of its key. Ties take the greatest value.
    """
    names = left.columns
    a = left.select(F.col(f"`{key[0]}`").alias("__k"), F.col(f"`{at[0]}`").alias("__t"), F.lit(1).alias("__side"), F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.struct(*[F.col(f"`{c}`") for c in names]).alias("__row"))
    b = right.select(F.col(f"`{key[1]}`").alias("__k"), F.col(f"`{at[1]}`").alias("__t"), F.lit(0).alias("__side"), F.col(f"`{value}`").alias("__v"), F.lit(None).cast(a.schema["__row"].dataType).alias("__row"))
    w = Window.partitionBy("__k").orderBy("__t", "__side", "__v")
    both = a.unionByName(b).withColumn("__last", F.last("__v", ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return both.filter("__side = 1").select(*[F.col(f"__row.`{c}`").alias(c) for c in names], F.col("__last").alias(out))
