"""Canonical content and content ids."""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

#: Columns of every capsule.
CAPSULE = ["capsule_id", "kind", "scope_root", "clinical_us", "recorded_us", "author_id", "parents", "amends", "retracts", "evidence", "body"]


def micros(c: Column) -> Column:
    return F.unix_micros(c.cast("timestamp"))


def money(c: Column) -> Column:
    """Two-decimal text; no binary float enters hashed content."""
    return c.cast("decimal(18,2)").cast("string")


def canon_expr(fields: dict[str, Column]) -> Column:
    """Canonical JSON of typed columns: keys sorted, no spaces, nulls left out."""
    return F.to_json(F.struct(*(fields[k].alias(k) for k in sorted(fields))))


def _number(x: int | float) -> str:
    """A number as the public canonical JSON scheme writes it: the shortest digits that read back as the same
    double, plain up to 21 digits and down to 1e-6, else with an exponent."""
    x = float(x)
    if x != x or x in (float("inf"), float("-inf")):
        raise ValueError("not a number of JSON")
    if x == 0:
        return "0"
    sign, digits = ("-" if x < 0 else ""), repr(abs(x))
    body, _, power = digits.partition("e")
    whole, _, part = body.partition(".")
    part = "" if part == "0" else part
    point = len(whole) + int(power or 0)  # digits before the point
    all_digits = (whole + part).lstrip("0")
    point -= len(whole + part) - len(all_digits)
    all_digits = all_digits.rstrip("0")
    n = len(all_digits)
    if n <= point <= 21:
        return sign + all_digits + "0" * (point - n)
    if 0 < point <= 21:
        return f"{sign}{all_digits[:point]}.{all_digits[point:]}"
    if -6 < point <= 0:
        return f"{sign}0.{'0' * -point}{all_digits}"
    tail = all_digits[0] + (f".{all_digits[1:]}" if n > 1 else "")
    return f"{sign}{tail}e{'+' if point > 0 else '-'}{abs(point - 1)}"


def _canonical(x) -> str:
    if isinstance(x, dict):
        # keys in the order of their UTF-16 units
        return "{" + ",".join(f"{json.dumps(k, ensure_ascii=False)}:{_canonical(x[k])}" for k in sorted(x, key=lambda k: k.encode("utf-16-be", "surrogatepass"))) + "}"
    if isinstance(x, list):
        return "[" + ",".join(map(_canonical, x)) + "]"
    if isinstance(x, bool) or x is None or isinstance(x, str):
        return json.dumps(x, ensure_ascii=False)
    return _number(x)


def canonical_text(source: str) -> str:
    """Canonical form of any JSON text: keys in order, no spaces, least escapes, one form of each number."""
    return _canonical(json.loads(source))


@F.pandas_udf(StringType())
def canon_udf(source: pd.Series) -> pd.Series:
    """The canonical form of JSON of any shape, a batch of rows at a time; bodies that the engine builds
    itself go through ``canon_expr`` and never come here."""
    return source.map(lambda s: None if s is None else canonical_text(s))


def envelope(kind: Column, body: Column, us: Column, parents: Column, author: Column, amends: Column, retracts: Column) -> Column:
    return canon_expr({"amends": amends, "author": author, "body": body, "kind": kind, "parents": parents, "retracts": retracts, "us": us})


def capsule_id(kind: Column, body: Column, us: Column, parents: Column, author: Column, amends: Column, retracts: Column) -> Column:
    return F.sha2(envelope(kind, body, us, parents, author, amends, retracts), 256)


def no_ids() -> Column:
    return F.array().cast("array<string>")


def capsules(df: DataFrame, kind: str, body: dict[str, Column], us: Column, parents: Column | None = None, scope: Column | None = None, author: Column | None = None, amends: Column | None = None, retracts: Column | None = None, recorded: Column | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """Capsules of one kind from source rows; a subject's scope is its own id. ``keep`` columns stay."""
    none = F.lit("")
    p = F.array_sort(F.array_distinct(parents)) if parents is not None else no_ids()
    df = df.withColumn("_body", canon_expr(body)).withColumn("_us", us.cast("long")).withColumn("_p", p)
    df = df.withColumns({"_a": author if author is not None else none, "_m": amends if amends is not None else none, "_r": retracts if retracts is not None else none})
    df = df.withColumn("_rec", (recorded if recorded is not None else F.col("_us")).cast("long"))
    own = capsule_id(F.lit(kind), F.col("_body"), F.col("_us"), F.col("_p"), F.col("_a"), F.col("_m"), F.col("_r"))
    df = df.withColumn("capsule_id", own)
    return df.select(
        "capsule_id", F.lit(kind).alias("kind"), (scope if scope is not None else F.col("capsule_id")).alias("scope_root"), F.col("_us").alias("clinical_us"), F.col("_rec").alias("recorded_us"),
        F.col("_a").alias("author_id"), F.col("_p").alias("parents"), F.col("_m").alias("amends"), F.col("_r").alias("retracts"), no_ids().alias("evidence"), F.col("_body").alias("body"), *keep,
    )


def rehash(c: DataFrame) -> Column:
    """The id that the stored columns hash to."""
    return capsule_id(F.col("kind"), F.col("body"), F.col("clinical_us"), F.col("parents"), F.col("author_id"), F.col("amends"), F.col("retracts"))
