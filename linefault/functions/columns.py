"""Column expressions shared by the operators. All are built-in functions, safe under ANSI mode."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

MICROS_PER_HOUR = 3_600_000_000.0


def hours_between(start: Column | str, end: Column | str) -> Column:
    """Hours from start to end as DOUBLE; works for both timestamp types."""
    return F.timestamp_diff("MICROSECOND", start, end) / F.lit(MICROS_PER_HOUR)


def add_hours(ts: Column | str, hours: Column) -> Column:
    return F.timestamp_add("MICROSECOND", F.round(hours * F.lit(MICROS_PER_HOUR)).cast("long"), ts)


def period_of(ts: Column | str, start: str, period_hours: int) -> Column:
    """Number of the period of period_hours from start that holds ts."""
    return F.floor(F.timestamp_diff("MICROSECOND", F.lit(start).cast("timestamp_ntz"), ts) / F.lit(period_hours * MICROS_PER_HOUR)).cast("int")


def ratio(part: Column, whole: Column) -> Column:
    """part / whole, null where it is undefined."""
    return F.try_divide(part.cast("double"), whole.cast("double"))


def tap_ratio_db(taps: Column | str, main: int = 8) -> Column:
    """Energy of the main tap over the energy of all others, in dB.

    taps are (real, imaginary) pairs one after another; main is the pair's index from 0. Null where the
    other taps carry no energy.
    """
    taps = F.col(taps) if isinstance(taps, str) else taps
    energy = lambda x: F.aggregate(x, F.lit(0.0), lambda acc, v: acc + v.cast("double") * v.cast("double"))
    own = energy(F.slice(taps, 2 * main + 1, 2))
    return F.lit(10.0) * F.log10(ratio(own, energy(taps) - own))


def rate_model(lam_n: Column, lam_a: Column, t_n: Column, t_fp: Column, t_fn: Column, t_a: Column) -> Column:
    """The expected ticketing-rate ratio of a threshold that errs for t_fp and t_fn."""
    abnormal = ratio(lam_n * t_fp + (lam_a + lam_n) * t_a, t_a + t_fp)
    normal = ratio(lam_n * t_n + (lam_a + lam_n) * t_fn, t_n + t_fn)
    return F.try_divide(abnormal, normal)


def rate_model_limit(lam_n: Column, lam_a: Column) -> Column:
    """The ratio without errors."""
    return ratio(lam_a, lam_n) + 1


def rate_model_slopes(lam_n: Column, lam_a: Column, t_n: Column, t_fp: Column, t_fn: Column, t_a: Column) -> tuple[Column, Column]:
    """Partial derivatives of rate_model by t_fp and by t_fn, in closed form."""
    normal = ratio(lam_n * t_n + (lam_a + lam_n) * t_fn, t_n + t_fn)
    abnormal = ratio(lam_n * t_fp + (lam_a + lam_n) * t_a, t_a + t_fp)
    by_fp = F.try_divide(ratio(-lam_a * t_a, (t_a + t_fp) * (t_a + t_fp)), normal)
    by_fn = -F.try_divide(abnormal * ratio(lam_a * t_n, (t_n + t_fn) * (t_n + t_fn)), normal * normal)
    return by_fp, by_fn


def fired(named: Sequence[tuple[str, Column]]) -> Column:
    """Names of the conditions that hold, in order."""
    return F.filter(F.array(*[F.when(cond, F.lit(name)) for name, cond in named]), lambda x: x.isNotNull()) if named else F.array().cast("array<string>")
