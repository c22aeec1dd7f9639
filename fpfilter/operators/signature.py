"""A filter's answers as relational queries: which (subfilter, address, fingerprint) triples are stored.

A table that stores first address and fingerprint of its keys, wherever eviction has moved them, answers exactly like
a semi-join on these triples. So load, false positives and every single answer have a plan of native operators, which
is both a fallback for any size and the form that another SQL engine can check.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fpfilter.functions.hashing import linear
from fpfilter.operators.filters import fresh, sub_of, with_mixed
from fpfilter.operators.spec import FilterSpec


def fingerprint(h: Column, spec: FilterSpec) -> Column:
    b = (1 << spec.fp_bits) - 1
    return linear(h, spec.factor("fingerprint", b), b) + 1


def address(h: Column, spec: FilterSpec) -> Column:
    return linear(h, spec.factor("address", spec.n_addr), spec.n_addr)


def other_address(at: Column, fp: Column, spec: FilterSpec) -> Column:
    n = spec.n_addr
    if spec.rule == "signed":
        return (at + 1 + linear(fp, spec.factor("offset", n - 1), n - 1)) % n
    if spec.rule == "mirror":
        return (2 * n - (at + fp % n)) % n
    if spec.rule == "xor_raw":
        return at.bitwiseXOR(fp.bitwiseAND(F.lit(n - 1)))
    return at.bitwiseXOR(1 + linear(fp, spec.factor("partner", n - 1), n - 1))


def with_signature(df: DataFrame, key: Column, spec: FilterSpec) -> DataFrame:
    """``df`` with ``sub, w0, fp``, which replace columns of these names; where the partner rule is symmetric w0 is the smaller address."""
    # never null, so that a join on them infers no filter, whose descent would inline all the steps of the hash
    known = lambda c: F.coalesce(c, F.lit(-1).cast("long"))
    (h,) = fresh(df, "h")
    got = with_mixed(df, key, spec, h)
    got = got.withColumn("sub", F.coalesce(sub_of(F.col(h), spec), F.lit(-1)))
    got = got.withColumn("w0", known(address(F.col(h), spec))).withColumn("fp", known(fingerprint(F.col(h), spec)))
    if spec.rule != "signed":
        got = got.withColumn("w0", known(F.least("w0", other_address(F.col("w0"), F.col("fp"), spec))))
    return got.drop(h)


def signature_set(keys: DataFrame, key: Column, spec: FilterSpec) -> DataFrame:
    """The distinct triples of non-null keys: what the packed table stores."""
    return with_signature(keys.where(key.isNotNull()).select(key.alias("key")), F.col("key"), spec).select("sub", "w0", "fp").distinct()


def contains_relational(df: DataFrame, key: Column, members: DataFrame, member_key: Column, spec: FilterSpec) -> DataFrame:
    """As the packed filter's ``contains``, by a join."""
    (known,) = fresh(df, "known")
    stored = signature_set(members, member_key, spec).withColumn(known, F.lit(True))
    marked = with_signature(df, key, spec).join(stored, ["sub", "w0", "fp"], "left")
    return marked.withColumn("hit", F.when(key.isNotNull(), F.coalesce(known, F.lit(False)))).drop("sub", "w0", "fp", known)
