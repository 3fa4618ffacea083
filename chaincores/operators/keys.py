"""Canonical keys: dominant values that agree when they differ in detail, and classes over several common attributes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import materialise
from .graph import name_classes, prune_subcliques, v_cliques


def prefix(n: int) -> Callable[[Column], Column]:
    """The first characters: the area of a phone number."""
    return lambda c: F.nullif(F.substring(c, 1, n), F.lit(""))


def email_server(c: Column) -> Column:
    """What follows the last at sign; null if there is none."""
    return F.nullif(F.lower(F.regexp_extract(c, r"@([^@\s]+)$", 1)), F.lit(""))


def url_domain(c: Column) -> Column:
    """Host of a url, with or without scheme, less a leading www."""
    return F.nullif(F.lower(F.regexp_extract(c, r"^(?:[A-Za-z][A-Za-z0-9+.-]*://)?(?:www\.)?([^/?#:\s]+)", 1)), F.lit(""))


def dominant_keys(records: DataFrame, rules: dict[str, Callable[[Column], Column]], similar: dict[str, float] | None = None) -> DataFrame:
    """``records`` with canonical values: by expression, or (``similar``) the class of values closer than a threshold, closed transitively.

    Null stays null; a value that a rule finds nothing in becomes null, and so shares nothing.
    """
    out = records.withColumns({c: rule(F.col(c)) for c, rule in rules.items()})
    for c, threshold in (similar or {}).items():
        classes = name_classes(records.select(F.col(c).alias("name")), threshold).select(F.col("name").alias("_was"), F.col("class").alias("_class"))
        out = out.join(classes, F.col(c) == F.col("_was"), "left").withColumn(c, F.col("_class")).drop("_was", "_class")
    return out


def common_key(records: DataFrame, columns: list[str]) -> DataFrame:
    """``records`` under one name that stands for several common attributes, all of which must agree; null if one is missing."""
    whole = F.when(F.forall(F.array(*columns), lambda x: x.isNotNull()), F.concat_ws("/", *columns))
    return records.withColumn("name", whole)


def graph_in_parts(values: DataFrame, parts: int) -> DataFrame:
    """The pruned incidence by parts of the values, each pruned by itself, and all together once more: equal to pruning at once.

    Containment and the least id among equals are kept by either order, so the first step only spares the second work.
    """
    dealt = values.withColumn("part", F.pmod(F.xxhash64("name", "attr", "value"), F.lit(parts)))
    found = None
    for p in range(parts):
        one = prune_subcliques(v_cliques(dealt.where(F.col("part") == p).drop("part")))
        found = one if found is None else found.unionByName(one)
    return prune_subcliques(materialise(found, "parts"))
