"""One-stage baselines, second-stage competitors, and measures."""

from __future__ import annotations

from dataclasses import dataclass
from heapq import heapify, heappop, heappush

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from ..functions.text import jaro_winkler_udf
from ..session import dealt, materialise
from .components import components
from .graph import LOCAL, graph, name_classes, record_components, value_rows


def _all(records: DataFrame, found: DataFrame) -> DataFrame:
    """Every record: its component, or itself."""
    return records.select("rid").join(found, "rid", "left").select("rid", F.coalesce("comp", "rid").alias("group_id"))


def same_name(records: DataFrame, threshold: float | None = None, classes: DataFrame | None = None) -> DataFrame:
    """Groups by name class only; ``classes`` are the :func:`name_classes` if they are known."""
    n = records.join(name_classes(records, threshold) if classes is None else classes, "name")
    low = n.groupBy("class").agg(F.min("rid").alias("comp"))
    return _all(records, n.join(low, "class").select("rid", "comp"))


def connected_graph(records: DataFrame) -> DataFrame:
    """Each component of the similarity graph (cores at k = 0, and single records)."""
    return _all(records, record_components(graph(records)))


def record_pairs(records: DataFrame, p: float = 0.8) -> DataFrame:
    """r1, r2, sim for records of one name that share a dominant value: name half, values half (noisy-or), small rewards for state and category."""
    v = value_rows(records).select("rid", "name", "attr", "value")
    pairs = v.join(v.withColumnRenamed("rid", "r2"), ["name", "attr", "value"]).where("rid < r2").groupBy(F.col("rid").alias("r1"), "r2").agg(F.count("*").alias("n"))
    at = records.select("rid", "state", "category")
    both = pairs.join(at.withColumnsRenamed({"rid": "r1", "state": "s1", "category": "c1"}), "r1").join(at.withColumnsRenamed({"rid": "r2", "state": "s2", "category": "c2"}), "r2")
    more = F.when(F.col("s1") == F.col("s2"), 0.1).otherwise(0.0) + F.when(F.col("c1") == F.col("c2"), 0.1).otherwise(0.0)
    return both.select("r1", "r2", F.least(F.lit(1.0), 0.5 + 0.5 * (1 - F.pow(F.lit(1 - p), F.col("n"))) * 0.8 + more).alias("sim"))


#: Weights of the attributes in the similarity of whole records; the location has none.
ATTRIBUTES = {"name": 0.4, "phone": 0.25, "url": 0.25, "category": 0.1}


def weighted_pairs(records: DataFrame, threshold: float = 0.8, weights: dict | None = None) -> DataFrame:
    """r1 < r2, sim: pairs whose weighted similarity over name (string similarity), phone, site and category is above the threshold.

    A missing value agrees with none. Only pairs with a common dominant value can reach the threshold, so candidates meet on these.
    """
    w = weights or ATTRIBUTES
    if w["name"] + w["category"] > threshold:
        raise ValueError("name and category alone would reach the threshold: candidates can't be found by dominant values")
    v = records.where("name is not null").select("rid", F.explode(F.array(F.struct(F.lit("phone").alias("attr"), F.col("phone").alias("value")), F.struct(F.lit("url").alias("attr"), F.col("url").alias("value")))).alias("p")).select("rid", "p.*").where("value is not null")
    pairs = v.join(v.withColumnRenamed("rid", "r2"), ["attr", "value"]).where("rid < r2").groupBy(F.col("rid").alias("r1"), "r2").agg(F.sum(F.when(F.col("attr") == "phone", w["phone"]).otherwise(w["url"])).alias("dom"))
    # what the dominant values lack, name and category must be able to add
    pairs = pairs.where(F.col("dom") + w["name"] + w["category"] > threshold)
    at = records.select("rid", "name", "category")
    both = pairs.join(at.withColumnsRenamed({"rid": "r1", "name": "n1", "category": "c1"}), "r1").join(at.withColumnsRenamed({"rid": "r2", "name": "n2", "category": "c2"}), "r2")
    sim = F.col("dom") + w["name"] * jaro_winkler_udf(F.col("n1"), F.col("n2")) + F.when(F.col("c1") == F.col("c2"), w["category"]).otherwise(0.0)
    return both.select("r1", "r2", sim.alias("sim")).where(F.col("sim") > threshold)


@dataclass(frozen=True)
class Alike:
    """Records that no pair tells apart, and pairs of these classes; a class is named by its smallest record.

    ``members(rid, node)`` of the records that share any value, ``classes(node, n, second, last)`` with the second and the
    largest record of a class, ``pairs(r1, r2, sim)`` of the smallest records. Two records of one class have similarity 1."""

    members: DataFrame
    classes: DataFrame
    pairs: DataFrame

    def parts(self, least: float = 0.0) -> tuple[DataFrame, DataFrame]:
        """(node, comp of the pairs above ``least``; those pairs with part, and a row r1 = r2 for each class of several records)."""
        edges = self.pairs.where(F.col("sim") > least)
        comp = materialise(components(edges, "r1", "r2", local=LOCAL), "parts")
        none = F.lit(None).cast("long")
        rows = edges.select("r1", "r2", "sim", none.alias("n"), none.alias("second"), none.alias("last"))
        rows = rows.unionByName(self.classes.where("n > 1").select(F.col("node").alias("r1"), F.col("node").alias("r2"), F.lit(1.0).alias("sim"), "n", "second", "last"))
        return comp, rows.join(comp.select(F.col("node").alias("r1"), F.col("comp").alias("part")), "r1")

    def spread(self, found: DataFrame) -> DataFrame:
        """rid, comp for all members by ``found(node, comp)``; a class that isn't found is its own."""
        return self.members.join(found, "node", "left").select("rid", F.coalesce("comp", "node").alias("comp"))


def alike(records: DataFrame) -> Alike:
    """Records of one name, state and category with the same values, as far as others of the name have these, are one class.

    A value that thousands share so gives pairs of the few classes that have it. Records without state or category are not
    wholly similar to each other, so each is a class of its own."""
    v = materialise(value_rows(records), "values")
    key = ["name", "attr", "value"]
    held = v.join(v.groupBy(*key).count().where("count > 1").select(*key), key).groupBy("rid").agg(F.sort_array(F.collect_set(F.struct("attr", "value"))).alias("held"))
    whole = records.select("rid", "name", "state", "category").join(held, "rid")
    own = F.when(F.col("state").isNull() | F.col("category").isNull(), F.col("rid"))
    kind = ["name", "held", "state", "category", own]
    members = materialise(whole.select("rid", F.min("rid").over(W.Window.partitionBy(*kind)).alias("node")), "members")
    classes = members.groupBy("node").agg(F.count("*").alias("n"), F.min(F.when(F.col("rid") > F.col("node"), F.col("rid"))).alias("second"), F.max("rid").alias("last"))
    first = materialise(records.join(members.where("rid = node").select("rid"), "rid", "left_semi"), "first")
    return Alike(members, materialise(classes, "classes"), materialise(record_pairs(first), "pairs"))


def edge_partition(records: DataFrame, threshold: float = 0.8, edges: Alike | None = None) -> DataFrame:
    """Transitive closure of pairs above the threshold (below 1). Here and below, ``edges`` are the classes and pairs of :func:`alike` if they are known."""
    edges = alike(records) if edges is None else edges
    found = components(edges.pairs.where(F.col("sim") > threshold), "r1", "r2", local=LOCAL)
    return _all(records, edges.spread(found))


def star(a, b, sim, second: dict, last: dict, merge: bool) -> dict:
    """Node -> smallest of its group, by edges a <= b between classes as between all their records; a = b says that a class has several.

    Edges go by falling similarity, then by the records. A class of several is assigned as a whole at similarity 1, and only its
    smallest record may be a centre; the others can matter where a record becomes a centre after it met the smallest one."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    name, (a, b) = nodes.tolist(), np.split(at, 2)
    centre, root = np.full(len(nodes), -1), list(range(len(nodes)))

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    def join(x, y):
        x, y = find(x), find(y)
        root[max(x, y)] = min(x, y)

    def turn(x, later: list, before: list) -> None:
        """The edges of record x to larger ones; ``before``: smaller classes of this similarity."""
        if centre[x] < 0:
            i = next((i for i, y in enumerate(later) if y != x and (centre[y] < 0 or centre[y] == y)), len(later))
            first = name[later[i]] if i < len(later) else None
            twin = second[name[x]] if later[0] == x else None
            if twin is None and first is None:
                return
            if twin is not None and (first is None or twin < first) or centre[later[i]] < 0:
                since = twin if first is None or (twin is not None and twin < first) else first
                centre[x] = x
                if merge:
                    for y in before + [y for y in later if y != x and name[y] < since]:
                        if centre[y] >= 0 and last.get(name[y], name[y]) > since:
                            join(x, centre[y])
                later = [y for y in later if name[y] >= since]
            else:
                centre[x] = later[i]
                later = later[i + 1 :]
        for y in later:
            if y == x:
                continue
            if centre[y] < 0:
                if centre[x] == x:
                    centre[y] = x
            elif merge and (centre[x] == x or centre[y] == y):
                join(centre[x], centre[y])

    order = np.lexsort((b, a, -sim))
    a, b, sim = a[order], b[order], sim[order]
    for x, y in zip(*(lambda cut: (cut, [*cut[1:], len(a)]))([0, *(np.flatnonzero(np.diff(sim)) + 1).tolist()]), strict=True):
        p, q = a[x:y], b[x:y]
        known = (centre[p] >= 0) & (centre[q] >= 0)
        if merge:
            hit = known & ((centre[p] == p) | (centre[q] == q))
            for c, d in np.unique(np.stack([centre[p[hit]], centre[q[hit]]], 1), axis=0).tolist():
                join(c, d)
        p, q = p[~known].tolist(), q[~known].tolist()
        later: dict = {}
        before: dict = {}
        for c, d in zip(p, q, strict=True):
            later.setdefault(c, []).append(d)
            if c != d and name[c] in last:
                before.setdefault(d, []).append(c)
        for c, ds in later.items():
            turn(c, ds, before.get(c, []))
    low: dict = {}
    group = [find(c) if c >= 0 else i for i, c in enumerate(centre.tolist())]
    for i, g in enumerate(group):
        low.setdefault(g, i)
    return {name[i]: name[low[g]] for i, g in enumerate(group)}


def edge_star(records: DataFrame, threshold: float = 0.8, merge: bool = False, edges: Alike | None = None) -> DataFrame:
    """Edges by falling similarity; a free end becomes a centre and attracts the other. With ``merge``, a record that is similar
    to two centres joins their clusters."""
    edges = alike(records) if edges is None else edges
    _, per = edges.parts(threshold)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        several = pdf[pdf["r1"] == pdf["r2"]]
        second, last = (dict(zip(several["r1"].tolist(), several[c].astype("int64").tolist(), strict=True)) for c in ("second", "last"))
        got = star(pdf["r1"].to_numpy(), pdf["r2"].to_numpy(), pdf["sim"].to_numpy(), second, last, merge)
        return pd.DataFrame(list(got.items()), columns=["node", "comp"])

    return _all(records, edges.spread(dealt(per, "part").groupBy("part").applyInPandas(run, "node long, comp long")))


def strict_rule(records: DataFrame) -> DataFrame:
    """Records that agree on all attributes (missing equals missing)."""
    keys = [F.coalesce(c, F.lit("")) for c in ("name", "phone", "url", "url2", "state", "category")]
    low = records.withColumn("k", F.concat_ws("|", *keys))
    return low.select("rid", F.min("rid").over(W.Window.partitionBy("k")).alias("group_id"))


#: Similarities are summed as whole numbers of this, so that equal means are equal whatever the order of the sums.
GRAIN = 10**12


def average_linkage(pairs, threshold: float, count: dict | None = None) -> list[list]:
    """Members of the clusters of two or more, from (a, b, similarity); pairs that aren't listed have none. Ties go to the smaller ids.

    ``count``: how many records an element stands for, if several; these are wholly similar to each other."""
    sim: dict = {}
    size = count or {}
    for a, b, s in pairs:
        total = round(s * GRAIN) * size.get(a, 1) * size.get(b, 1)
        sim.setdefault(a, {})[b] = total
        sim.setdefault(b, {})[a] = total
    size, members, threshold = {n: size.get(n, 1) for n in sim}, {n: [n] for n in sim}, round(threshold * GRAIN)
    several = {n for n, m in size.items() if m > 1}
    heap = [(-mean, a, b) for a, row in sim.items() for b, total in row.items() if a < b and (mean := total / (size[a] * size[b])) >= threshold]
    heapify(heap)
    while heap:
        s, a, b = heappop(heap)
        if a not in sim or b not in sim[a] or sim[a][b] / (size[a] * size[b]) != -s:
            continue  # one of them has changed since
        for c, more in sim.pop(b).items():
            del sim[c][b]
            if c != a:
                sim[a][c] = sim[c][a] = sim[a].get(c, 0) + more
        size[a] += size.pop(b)
        members[a] += members.pop(b)
        for c, total in sim[a].items():
            if (mean := total / (size[a] * size[c])) >= threshold:
                heappush(heap, (-mean, min(a, c), max(a, c)))
    return [m for m in members.values() if len(m) > 1 or m[0] in several]


def agglomerative_cores(records: DataFrame, threshold: float = 0.9, edges: Alike | None = None) -> DataFrame:
    """rid, core by average linkage over the record pairs of each component."""
    edges = alike(records) if edges is None else edges
    comp, per = edges.parts()

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf["r1"] == pdf["r2"]
        count = dict(zip(pdf.loc[own, "r1"].tolist(), pdf.loc[own, "n"].astype("int64").tolist(), strict=True))
        pairs = pdf[~own]
        got = average_linkage(zip(pairs["r1"].tolist(), pairs["r2"].tolist(), pairs["sim"].tolist(), strict=True), threshold, count)
        return pd.DataFrame([(n, min(m)) for m in got for n in m], columns=["node", "core"])

    found = dealt(per, "part").groupBy("part").applyInPandas(run, "node long, core long")
    alone = edges.classes.where("n > 1").join(comp, "node", "left_anti").select("node", F.col("node").alias("core"))
    return edges.members.join(found.unionByName(alone), "node").select("rid", "core")


def features(records: DataFrame) -> DataFrame:
    """rid, feature: name, dominant values, state and category as one vocabulary."""
    cols = [("name", "name"), ("phone", "phone"), ("url", "url"), ("url", "url2"), ("state", "state"), ("category", "category")]
    pairs = F.array(*[F.struct(F.lit(a).alias("a"), F.col(c).alias("v")) for a, c in cols])
    return records.select("rid", F.explode(pairs).alias("p")).where("p.v is not null").select("rid", F.concat_ws("=", "p.a", "p.v").alias("feature")).distinct()


def tfidf_assign(records: DataFrame, cores: DataFrame) -> DataFrame:
    """Satellites go to the core with the largest sum of squared inverse document frequencies of common features.

    State and category alone would join all satellites with nearly all cores. Of the cores that share nothing else, the best one
    is the same for all satellites of one state and category, so it is found once for these; only cores that share more are scored by satellite."""
    cores = materialise(cores, "cores")
    f = materialise(features(records), "features")
    n = records.count()
    idf = f.groupBy("feature").agg(F.log(F.lit(float(n)) / F.count("*")).alias("idf"))
    of_core = f.join(cores, "rid").groupBy("core", "feature").agg(F.count("*").alias("c"))
    size = cores.groupBy("core").agg(F.count("*").alias("size"))
    w = of_core.join(size, "core").join(idf, "feature").select("core", "feature", (F.col("c") / F.col("size") * F.col("idf") * F.col("idf")).alias("w"))
    w, left = materialise(w.where("w > 0"), "weights"), materialise(f.join(cores, "rid", "left_anti"), "left")
    common = F.col("feature").startswith("state=") | F.col("feature").startswith("category=")
    score, first = F.round(F.sum("w"), 9).alias("score"), F.min(F.struct((-F.col("score")).alias("s"), "core"))
    near = left.where(~common).join(w, "feature").select("rid", "core").distinct()
    near = materialise(near.join(left, "rid").join(w, ["core", "feature"]).groupBy("rid", "core").agg(score), "near")
    kinds = left.where(common).groupBy("rid").agg(F.sort_array(F.collect_list("feature")).alias("kind"))
    far = kinds.select("kind").distinct().select("kind", F.explode("kind").alias("feature")).join(w, "feature").groupBy("kind", "core").agg(score)
    far = kinds.join(far.groupBy("kind").agg(first.alias("b")), "kind").select("rid", "b.core", (-F.col("b.s")).alias("score"))
    best = near.unionByName(far).where("score > 0").groupBy("rid").agg(first.alias("b")).select("rid", "b.core")
    return _all(records, cores.unionByName(best).withColumnRenamed("core", "comp"))


def vote_round(records: DataFrame, assigned: DataFrame, min_count: int = 5) -> DataFrame:
    """One round: representative features of a cluster are those of ``min_count`` members or more; records without cluster vote."""
    f = features(records)
    rep = f.join(assigned, "rid").groupBy("core", "feature").agg(F.count("*").alias("c")).where(F.col("c") >= min_count).select("core", "feature")
    votes = f.join(assigned, "rid", "left_anti").join(rep, "feature").groupBy("rid", "core").agg(F.count("*").alias("votes"))
    return votes.withColumn("at", F.row_number().over(W.Window.partitionBy("rid").orderBy(F.desc("votes"), "core"))).where("at = 1").select("rid", "core")


def vote_assign(records: DataFrame, cores: DataFrame, min_count: int = 5) -> DataFrame:
    """Rounds of voting until nothing changes."""
    assigned = materialise(cores.select("rid", "core"), "assigned")
    while True:  # each round but the last assigns records
        more = materialise(vote_round(records, assigned, min_count), "votes")
        if more.isEmpty():
            break
        assigned = materialise(assigned.unionByName(more), "assigned")
    return _all(records, assigned.withColumnRenamed("core", "comp"))


def pairwise_prf(pred: DataFrame, gold: DataFrame) -> DataFrame:
    """``pred(rid, group_id)``, ``gold(rid, gold)`` -> tp, fp, fn, precision, recall, f from the contingency table; no pair is listed."""
    j = gold.join(pred, "rid", "left")
    pairs = lambda n: F.coalesce(F.sum(F.expr(f"{n} * ({n} - 1) div 2")), F.lit(0))
    cell = j.where("group_id is not null").groupBy("group_id", "gold").agg(F.count("*").alias("n"))
    t = cell.agg(pairs("n").alias("tp"))
    p = cell.groupBy("group_id").agg(F.sum("n").alias("n")).agg(pairs("n").alias("p"))
    g = gold.groupBy("gold").agg(F.count("*").alias("n")).agg(pairs("n").alias("g"))
    one = t.crossJoin(p).crossJoin(g)  # one row each
    ratio = lambda a, b: F.round(F.when(F.col(b) > 0, F.col(a) / F.col(b)), 6)
    return one.select("tp", (F.col("p") - F.col("tp")).alias("fp"), (F.col("g") - F.col("tp")).alias("fn"), ratio("tp", "p").alias("precision"), ratio("tp", "g").alias("recall"), F.round(F.when(F.col("p") + F.col("g") > 0, 2 * F.col("tp") / (F.col("p") + F.col("g"))), 6).alias("f"))


def group_profile(records: DataFrame, groups: DataFrame) -> DataFrame:
    """Size and distinct values per group."""
    j = records.join(groups, "rid")
    urls = j.select("group_id", F.explode(F.array_compact(F.array("url", "url2"))).alias("u")).groupBy("group_id").agg(F.countDistinct("u").alias("n_urls"))
    p = j.groupBy("group_id").agg(F.count("*").alias("n_records"), F.countDistinct("name").alias("n_names"), F.countDistinct("phone").alias("n_phones"), F.countDistinct("category").alias("n_categories"))
    return p.join(urls, "group_id", "left").select("group_id", "n_records", "n_names", "n_phones", F.coalesce("n_urls", F.lit(0)).alias("n_urls"), "n_categories")


def gold_stats(records: DataFrame) -> DataFrame:
    """records, groups of two or more, singletons, smallest and largest such group."""
    n = records.groupBy("gold").agg(F.count("*").alias("n"))
    big = F.when(F.col("n") > 1, F.col("n"))
    return n.agg(F.sum("n").alias("n_records"), F.count(big).alias("n_groups"), F.count_if(F.col("n") == 1).alias("n_single"), F.min(big).alias("smallest"), F.max(big).alias("largest"))


def block_stats(blocks: DataFrame) -> DataFrame:
    """Blocks of more than one record: how many, largest, mean, share below a hundred."""
    n = blocks.groupBy("block").agg(F.count("*").alias("n")).where("n > 1")
    return n.agg(F.count("*").alias("n_blocks"), F.max("n").alias("largest"), F.round(F.avg("n"), 6).alias("mean_size"), F.round(F.avg((F.col("n") < 100).cast("int")), 6).alias("below_100"))
