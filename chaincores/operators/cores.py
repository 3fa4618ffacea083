"""Core identification: components, distributed screening of giant ones, exact solving of the others in tasks."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import robust
from ..session import dealt, materialise
from .components import components
from .graph import overlaps, record_components, simplify

#: Index rows of a component (simplified where the strategy is) beyond which it is screened as DataFrames first.
LOCAL_LIMIT = 100_000


def v_unions(incidence: DataFrame, k: int) -> DataFrame:
    """clique, union: cliques linked by overlaps of k+1 records or more."""
    near = overlaps(incidence).where(F.col("n") > k)
    names = materialise(incidence.select("clique").distinct(), "cliques")
    found = components(near, "c1", "c2")
    return names.join(found, names.clique == found.node, "left").select("clique", F.coalesce("comp", "clique").alias("union"))


def borders(incidence: DataFrame, unions: DataFrame, comps: DataFrame, k: int, guard: bool = True) -> DataFrame:
    """union, n_border, n_inner, n_graph, violates; comps is rid, comp."""
    r = incidence.join(unions, "clique").select("rid", "union").distinct()
    many = r.groupBy("rid").agg(F.count("*").alias("u"))
    per = r.join(many, "rid").join(comps, "rid").groupBy("union", "comp").agg(F.count_if(F.col("u") > 1).alias("n_border"), F.count_if(F.col("u") == 1).alias("n_inner"))
    size = comps.groupBy("comp").agg(F.count("*").alias("n_graph"))
    bad = (F.col("n_border") > 0) & (F.col("n_border") <= k)
    if guard:
        bad = bad & (F.col("n_inner") > 0) & (F.col("n_graph") > F.col("n_border") + F.col("n_inner"))
    return per.join(size, "comp").select("union", "n_border", "n_inner", "n_graph", bad.alias("violates"))


def screen_round(incidence: DataFrame, k: int, guard: bool = True) -> tuple[DataFrame, DataFrame]:
    """(incidence without the borders of violating unions, those border records)."""
    unions = materialise(v_unions(incidence, k), "unions")
    comps = materialise(record_components(incidence), "comps")
    bad = borders(incidence, unions, comps, k, guard).where("violates").select("union")
    r = incidence.join(unions, "clique").select("rid", "union").distinct()
    edge = r.groupBy("rid").count().where("count > 1").select("rid")
    gone = materialise(r.join(bad, "union").join(edge, "rid", "left_semi").select("rid").distinct(), "gone")
    return incidence.join(gone, "rid", "left_anti"), gone


def find_cores(incidence: DataFrame, k: int = 2, strategy: str = "full", guard: bool = True, local_limit: int = LOCAL_LIMIT, metrics: bool = False) -> DataFrame:
    """``incidence(rid, clique)`` -> rid, core (smallest rid of the core); with ``metrics`` counters per component.

    Records outside any core don't appear. At k = 0 cores are the components. A component beyond ``local_limit`` rows is a
    core if it is one union of cliques; others are screened in distributed rounds while that removes records. What is
    left is solved exactly in one task per component, whatever its size.
    """
    simple = robust.STRATEGIES[strategy][0]

    def local(pdf: pd.DataFrame) -> pd.DataFrame:
        cliques = [frozenset(g) for _, g in pdf.groupby("clique", sort=True)["node"]]
        weight = dict(zip(pdf["node"], pdf["weight"], strict=True))
        m: dict = {}
        got = robust.solve(cliques, weight, k, strategy, guard, metrics=m)
        if metrics:
            return pd.DataFrame([{"comp": pdf["comp"].iloc[0], "nodes": len(weight), "cores": len(got), **m}])
        return pd.DataFrame([(n, min(c)) for c in got for n in c], columns=["node", "core"])

    if k == 0 and not metrics:
        comps = materialise(record_components(incidence), "comps")
        linked = comps.groupBy("comp").count().where("count > 1").select("comp")
        return comps.join(linked, "comp").select("rid", F.col("comp").alias("core"))
    incidence, whole = materialise(incidence, "incidence"), None
    while True:
        comps = materialise(record_components(incidence), "comps")
        if simple:
            nodes, members = simplify(incidence)
            rows = nodes.select("node", "weight", F.explode("cliques").alias("clique"))
        else:
            rows, members = incidence.select(F.col("rid").alias("node"), F.lit(1).cast("long").alias("weight"), "clique"), None
        rows = materialise(rows.join(comps.withColumnRenamed("rid", "node"), "node"), "rows")
        big = materialise(rows.groupBy("comp").count().where(F.col("count") > local_limit).select("comp"), "giants")
        if big.isEmpty():
            break
        labelled = incidence.join(comps, "rid")
        giant = materialise(labelled.join(big, "comp").select("rid", "clique", "comp"), "giant")
        one = None
        if not metrics:
            # a component of one union holds together without any border
            of = giant.join(v_unions(giant.select("rid", "clique"), k), "clique").groupBy("comp").agg(F.countDistinct("union").alias("n"), F.countDistinct("rid").alias("m"))
            one = materialise(of.where("n = 1 and m > 1").select("comp"), "single")
            found = materialise(giant.join(one, "comp").select("rid", F.col("comp").alias("core")).distinct(), "whole")
            whole = found if whole is None else whole.unionByName(found)
            giant = giant.join(one, "comp", "left_anti")
        rest, gone = screen_round(giant.select("rid", "clique"), k, guard)
        if gone.isEmpty() and (one is None or one.isEmpty()):
            break
        incidence = materialise(labelled.join(big, "comp", "left_anti").select("rid", "clique").unionByName(rest), "incidence")
    if metrics:
        return dealt(rows, "comp").groupBy("comp").applyInPandas(local, "comp long, nodes long, cores long, screens long, splits long, largest_screen long, largest_split long")
    found = dealt(rows, "comp").groupBy("comp").applyInPandas(local, "node long, core long")
    found = found.withColumnRenamed("node", "rid") if members is None else members.join(found, "node").select("rid", "core")
    return found if whole is None else found.unionByName(whole)
