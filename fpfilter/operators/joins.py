"""Joins behind a filter: what the filter rules out never meets the exact join."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fpfilter.operators.filters import Spec, build_filter, contains, fresh
from fpfilter.sources.tables import written


def filtered_join(probe: DataFrame, build: DataFrame, on: str | tuple[str, str], spec: Spec, how: str = "inner", table: DataFrame | None = None, strategy: str = "auto") -> DataFrame:
    """``probe`` joined with ``build``; only probe rows that may have a partner take part in the exact join.

    Results equal the plain join's. inner, left_semi: rows that the filter rules out go. left, left_anti: they go
    straight to the output, which is sound because a filter never misses a member; only possible partners are looked
    up exactly. ``on``: one common column, or (probe column, build column). Unless a filter is given, the build side
    is written once, as it is read to be counted, for the filter and for the join.
    """
    left, right = (on, on) if isinstance(on, str) else on
    (hit,) = fresh(probe, "hit")
    if table is None:
        build = written(build, "build")
        table = build_filter(build.select(right), right, spec)
    marked = contains(probe, left, table, strategy, to=hit)
    maybe = marked.where(F.col(hit)).drop(hit)
    match = maybe[left] == build[right] if left != right else left
    if how in ("inner", "left_semi"):
        return maybe.join(build, match, how)
    if how not in ("left", "left_outer", "left_anti"):
        raise ValueError(f"a filter on the build side does not help a {how} join")
    absent = marked.where(F.col(hit).isNull() | ~F.col(hit)).drop(hit)
    exact = maybe.join(build, match, how)
    return exact.unionByName(absent, allowMissingColumns=True).select(exact.columns)


def surely_absent(df: DataFrame, key: Column | str, table: DataFrame, strategy: str = "auto") -> DataFrame:
    """The rows whose non-null key is not in the filter: exact, as there are no false negatives."""
    (hit,) = fresh(df, "hit")
    return contains(df, key, table, strategy, to=hit).where(~F.col(hit)).drop(hit)


def confusion(probe: DataFrame, key: str, members: DataFrame, member_key: str, table: DataFrame) -> DataFrame:
    """``outcome, rows``: true and false positives and negatives of a filter in front of the exact key set."""
    of, known, marked = fresh(probe, "of", "known", "hit")
    exact = members.select(F.col(member_key).alias(of)).where(F.col(of).isNotNull()).distinct().withColumn(known, F.lit(True))
    got = contains(probe.where(F.col(key).isNotNull()), key, table, to=marked).join(exact, F.col(key) == F.col(of), "left")
    member, hit = F.coalesce(known, F.lit(False)), F.col(marked)
    outcome = F.when(member & hit, "true_positive").when(member, "false_negative").when(hit, "false_positive").otherwise("true_negative")
    return got.groupBy(outcome.alias("outcome")).agg(F.count(F.lit(1)).alias("rows"))
