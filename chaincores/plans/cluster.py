"""Clustering of one block: popularity-weighted similarity, greedy or exhaustive start, adjustment under a silhouette index."""

from __future__ import annotations

import heapq
from collections import Counter
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Weights:
    """Agreement and disagreement weights of common and dominant values, and the agreement weight of each multi-value attribute.

    In double mode the values that only one group has (distinct) weigh apart from the others.
    """

    com: tuple = (0.5, 0.5)
    dom: tuple = (0.45, 0.5)
    com_distinct: tuple = (0.9, 0.5)
    dom_distinct: tuple = (0.9, 0.5)
    multi: float = 0.1
    mode: str = "double"

    def effective(self, role: str, sim: float, distinct: bool = False) -> float:
        agree, differ = getattr(self, f"{role}_distinct" if distinct and self.mode == "double" else role)
        return sim * agree + (1 - sim) * differ

    @property
    def ambiguous(self) -> float:
        """What a dominant value counts that others have too, against one that they don't."""
        return min(1.0, self.dom[0] / self.dom_distinct[0]) if self.mode == "double" and self.dom_distinct[0] else 1.0


PRESETS = {"fixed": Weights(), "three_equal": Weights((1 / 3, 1 / 3), (1 / 3, 1 / 3), multi=1 / 3, mode="single"), "two_equal": Weights((0.5, 0.5), (0.5, 0.5), multi=0.1, mode="single")}


@dataclass(frozen=True)
class Settings:
    p: float = 0.8
    theta: float = 0.6
    start: float = 0.6
    border: float = 0.3
    alpha: float = 0.01
    beta: float = 0.02
    value_weight: str = "popularity"
    dominant: str = "united"
    weights: Weights = Weights()
    init: str = "greedy"
    adjust: bool = True

    def but(self, **changes) -> Settings:
        return replace(self, **changes)


def noisy_or(terms) -> float:
    left = 1.0
    for x in terms:
        left *= 1 - min(x, 1.0)
    return 1 - left


class Element:
    """A core or satellite: record count and value counts by (role, attribute, value)."""

    def __init__(self, eid, is_core: bool, size: int, values: dict):
        self.eid, self.is_core, self.size, self.values = eid, is_core, size, Counter(values)
        self.common, self.dominant = [k for k in self.values if k[0] == "com"], [k for k in self.values if k[0] == "dom"]


class Cluster:
    def __init__(self):
        self.members: dict = {}
        self.values: Counter = Counter()
        self.size = 0

    def add(self, e: Element) -> None:
        self.members[e.eid] = e
        self.values.update(e.values)
        self.size += e.size

    def remove(self, e: Element) -> None:
        del self.members[e.eid]
        self.values.subtract(e.values)
        self.size -= e.size

    def valid(self) -> bool:
        return any(e.is_core for e in self.members.values()) or len(self.members) <= 1


def similarity(e: Element, c: Cluster, s: Settings, shared_values: frozenset = frozenset(), sole: frozenset = frozenset()) -> float:
    """Of an element to a cluster's other members. Dominant values in ``shared_values`` are not distinct, common ones in ``sole`` are."""
    own = e.eid in c.members
    size = c.size - (e.size if own else 0)
    if size <= 0:
        return 1.0 if own else 0.0

    def w(key):
        n = c.values[key] - (e.values[key] if own else 0)
        return 0.0 if n <= 0 else 1.0 if s.value_weight == "none" else n / size

    def mine(key):
        return 1.0 if s.value_weight == "none" else e.values[key] / e.size

    com = e.common
    dot = sum(mine(k) * w(k) for k in com)
    if dot:
        a = sum(mine(k) ** 2 for k in com) ** 0.5
        b = sum((max(0, n - (e.values[k] if own else 0)) / size) ** 2 for k, n in c.values.items() if k[0] == "com") ** 0.5 if s.value_weight != "none" else max(1.0, sum(1 for k, n in c.values.items() if k[0] == "com" and n > 0)) ** 0.5
        dot = min(1.0, dot / (a * b))
    terms: dict = {}
    strong_value = False
    for k in e.dominant:
        if x := w(k):
            f = s.weights.ambiguous if k in shared_values else 1.0
            strong_value |= k not in shared_values
            terms.setdefault(k[1] if s.dominant == "separated" else "", []).append(s.p * mine(k) * x * f)
    if s.dominant == "separated":
        attrs = {k[1] for k in e.values if k[0] == "dom"}
        dom = sum(noisy_or(terms.get(a, ())) for a in attrs) / max(1, len(attrs))
    else:
        dom = noisy_or(terms.get("", ()))
    wc, wd = s.weights.effective("com", dot, any(k in sole and w(k) for k in com)), s.weights.effective("dom", dom, strong_value)
    strong = (wc * dot + wd * dom) / (wc + wd) if wc + wd else 0.0
    if strong >= s.theta:
        for attr in {k[1] for k in e.values if k[0] == "multi"}:
            strong += s.weights.multi * min(1.0, sum(mine(k) * w(k) for k in e.values if k[0] == "multi" and k[1] == attr))
    return min(1.0, strong)


def silhouette(a: float, b: float, alpha: float = 0.01, beta: float = 0.02) -> float:
    return (a - b + alpha) / (max(a, b) + beta)


class Block:
    def __init__(self, elements: list[Element], s: Settings, outside: frozenset = frozenset()):
        """outside: common values that elements elsewhere have too, which share nothing else with these."""
        self.s, self.elements, self.outside = s, {e.eid: e for e in elements}, outside
        self.of: dict = {}
        self.clusters: dict = {}
        self.next = 0
        seen = Counter(k for e in elements if e.is_core for k in e.values if k[0] == "dom")
        self.shared = frozenset(k for k, n in seen.items() if n > 1)
        bear = Counter(k for e in elements if e.is_core for k in e.values if k[0] == "com")
        self.sole = frozenset(k for k, n in bear.items() if n == 1) - outside
        self.holders: dict = {}  # value -> clusters that hold it
        self.bearers: dict = {}  # value -> elements that have it
        for e in elements:
            for k in e.values:
                self.bearers.setdefault(k, []).append(e.eid)
        self.stamps, self.changes = {}, 0  # cluster -> number of its last change
        self.sims: dict = {}  # eid -> cluster -> (stamp, similarity)
        self.score: dict = {}  # eid -> (silhouette, nearest other cluster, similarity to own, to that one)
        self.seen: list = []  # similarities that were replaced since the last change, with the row that they were in
        self.touched: dict = {}  # cluster -> its values and members before it changed
        self.moved: set = set()  # elements that were put elsewhere
        self.several: dict = {}  # common value -> whether several clusters held it before
        self.pairs: dict = {}  # pair of clusters -> its border elements
        self.filed: dict = {}  # border element -> its pair
        self.paired: dict = {}  # cluster -> pairs that it is in

    def new(self, members=()) -> int:
        c = self.next
        self.next += 1
        self.clusters[c] = Cluster()
        for e in members:
            self.put(e, c)
        return c

    def _change(self, c: int) -> Cluster:
        cl = self.clusters.setdefault(c, Cluster())
        if c not in self.touched:
            self.touched[c] = [k for k, n in cl.values.items() if n > 0], list(cl.members)
        self.changes += 1
        self.stamps[c] = self.changes
        return cl

    def put(self, e: Element, c: int) -> None:
        old = self.of.get(e.eid)
        if old == c:
            return
        for k in e.values:
            self.several.setdefault(k, len(self.holders.get(k, ())) > 1)
        if old is not None:
            cl = self._change(old)
            cl.remove(e)
            for k in e.values:
                if cl.values[k] <= 0:
                    self.holders[k].discard(old)
            if not cl.members:
                del self.clusters[old]
        self._change(c).add(e)
        self.moved.add(e.eid)
        self.of[e.eid] = c
        for k in e.values:
            self.holders.setdefault(k, set()).add(c)

    def refresh(self) -> dict:
        """Score anew the elements whose similarities may have changed; eid -> score before."""
        stale, keys = set(), set()
        for c, (values, members) in self.touched.items():
            stale.update(members)
            keys.update(values)
            if c in self.clusters:
                stale.update(self.clusters[c].members)
                keys.update(k for k, n in self.clusters[c].values.items() if n > 0)
        for k in keys:
            if k[0] == "dom" or (k[0] == "com" and k in self.several and self.several[k] != (len(self.holders.get(k, ())) > 1)):
                stale.update(self.bearers[k])
        changed, moved = list(self.touched), self.moved
        self.touched, self.several, self.moved = {}, {}, set()
        before = {eid: self.score.get(eid) for eid in stale}
        for eid in stale:
            self.score[eid] = self.rate(self.elements[eid], None if eid in moved else changed)
        return before

    def like(self, e: Element, c: int) -> float:
        known = self.sims.setdefault(e.eid, {})
        if (got := known.get(c)) is None or got[0] != self.stamps[c]:
            self.seen.append((known, c, got))
            got = known[c] = self.stamps[c], similarity(e, self.clusters[c], self.s, self.shared, self.sole)
        return got[1]

    def near(self, e: Element) -> list[tuple[float, int]]:
        """Similarity to the clusters that share a dominant value with the element, best first."""
        ids = {c for k in e.dominant for c in self.holders.get(k, ())}
        return sorted(((self.like(e, c), c) for c in ids), key=lambda x: (-x[0], x[1]))

    def base(self, e: Element) -> float:
        """Similarity to a cluster that agrees on the common value alone, if there is another such cluster."""
        if not any(k in self.outside or len(self.holders[k]) > 1 for k in e.values if k[0] == "com"):
            return 0.0
        wc, wd = self.s.weights.effective("com", 1.0), self.s.weights.effective("dom", 0.0)
        return wc / (wc + wd) if wc + wd else 0.0

    def initialise(self) -> None:
        """Cores are clusters; a satellite joins the best one above the threshold, else it is a cluster of its own.

        It joins no satellite: a cluster without core may hold only one.
        """
        cores = sorted((e for e in self.elements.values() if e.is_core), key=lambda e: e.eid)
        with_core = {self.new([e]) for e in cores}
        rest = sorted((e for e in self.elements.values() if not e.is_core), key=lambda e: (-sum(k[0] == "dom" for k in e.values), e.eid))
        if self.s.init == "exhaustive":
            moved = True
            while moved:
                moved, left = False, []
                for e in rest:
                    best = [x for x in self.near(e) if x[1] in with_core]
                    if best and best[0][0] > self.s.start:
                        self.put(e, best[0][1])
                        moved = True
                    else:
                        left.append(e)
                rest = left
        for e in rest:
            best = [x for x in self.near(e) if x[1] in with_core]
            self.put(e, best[0][1]) if best and best[0][0] > self.s.start else self.new([e])

    def other(self, e: Element, own: int, changed: list | None) -> tuple:
        """Similarity to the nearest cluster but the own one, and that cluster (the smaller of equals).

        ``changed``: clusters that are not what they were at the last score, if the element stayed where it was. The others
        are no nearer than before, so they count by the last score alone, unless the nearest one itself went away."""
        was = self.score.get(e.eid)
        if changed is not None and was is not None:
            b, at = was[3], was[1]
            if at not in changed or (any(at in self.holders[k] for k in e.dominant) and self.like(e, at) >= b):
                if at in changed:
                    b, at = 0.0, None
                for c in changed:
                    if c != own and any(c in self.holders[k] for k in e.dominant):
                        x = self.like(e, c)
                        if at is None or x > b or (x == b and c < at):
                            b, at = x, c
                return b, at
        b, at = 0.0, None
        for c in {c for k in e.dominant for c in self.holders[k]}:
            if c != own:
                x = self.like(e, c)
                if at is None or x > b or (x == b and c < at):
                    b, at = x, c
        return b, at

    def rate(self, e: Element, changed: list | None = None) -> tuple:
        """(silhouette, nearest other cluster, similarity to the own cluster, to that one); ``changed`` as in :meth:`other`."""
        own = self.of[e.eid]
        a = 1.0 if len(self.clusters[own].members) == 1 else self.like(e, own)
        b, at = self.other(e, own, changed)
        return silhouette(a, max(b, self.base(e)), self.s.alpha, self.s.beta), at, a, b

    def index(self) -> float:
        return sum(x[0] for x in self.score.values()) / max(1, len(self.score))

    def candidates(self) -> list[tuple[float, int, int, list]]:
        """(benefit, cluster, cluster, border elements), best first."""
        self.file(self.score)
        return sorted((self.candidate(k) for k in self.pairs), key=lambda x: (-x[0], x[1:3]))

    def candidate(self, pair: tuple) -> tuple[float, int, int, list]:
        m = sorted(self.pairs[pair])
        return sum(1 - self.score[e][0] for e in m), *pair, m

    def file(self, eids) -> set:
        """File elements under the pair of clusters that they lie on the border of; the pairs that this touches."""
        touched = set()
        for eid in eids:
            x, at, _, _ = self.score[eid]
            now = tuple(sorted((self.of[eid], at))) if at is not None and x <= self.s.border else None
            was = self.filed.get(eid)
            if was is not None:
                touched.add(was)
                if was != now:
                    self.pairs[was].discard(eid)
                    if not self.pairs[was]:
                        del self.pairs[was]
                        for c in was:
                            self.paired[c].discard(was)
            if now is not None:
                touched.add(now)
                self.filed[eid] = now
                self.pairs.setdefault(now, set()).add(eid)
                for c in now:
                    self.paired.setdefault(c, set()).add(now)
            elif was is not None:
                del self.filed[eid]
        return touched

    def change(self, moves: list) -> tuple:
        """Put elements into clusters, ``moves`` of (eid, cluster): (gain of the summed silhouettes, all valid, what undoes it)."""
        was = [(eid, self.of[eid]) for eid, _ in moves]
        at = {c: self.stamps[c] for c in {c for x in (was, moves) for _, c in x} if c in self.stamps}
        self.seen = []
        for eid, c in moves:
            self.put(self.elements[eid], c)
        valid = all(self.clusters[c].valid() for c in self.touched if c in self.clusters)
        before = self.refresh()
        return sum(self.score[e][0] - x[0] for e, x in sorted(before.items())), valid, (was, at, before)

    def undo(self, was: list, at: dict, before: dict) -> None:
        for eid, c in reversed(was):
            self.put(self.elements[eid], c)
        for known, c, got in reversed(self.seen):
            if got is None:
                del known[c]
            else:
                known[c] = got
        self.stamps.update(at)
        self.score.update(before)
        self.touched, self.several, self.moved, self.seen = {}, {}, set(), []

    def settle(self, relevant) -> set:
        """Move elements that are more similar to another cluster there, as long as the index rises by it; all that were scored anew."""
        todo, scored = set(relevant), set(relevant)
        while todo:
            eid = min(todo)
            todo.discard(eid)
            _, at, a, b = self.score[eid]
            if at is None or b <= a:
                continue
            gain, valid, back = self.change([(eid, at)])
            if valid and gain > self.least:
                todo.update(back[2])
                scored.update(back[2])
            else:
                self.undo(*back)
        return scored

    @property
    def least(self) -> float:
        """A smaller gain is rounding."""
        return 1e-12 * max(1, len(self.elements))

    def adjust(self) -> None:
        """Re-cluster candidate pairs while the index rises, until no pair is left that was not tried as it is."""
        self.refresh()
        tried: set = set()
        key = lambda x: (self.stamps[x[1]], self.stamps[x[2]], tuple(x[3]))
        self.file(self.score)
        queue, entered = [], {}  # benefit falling, pair, number of its last entry

        def enter(pairs) -> None:
            for pair in pairs:
                entered[pair] = entered.get(pair, 0) + 1
                if pair in self.pairs:
                    heapq.heappush(queue, (-self.candidate(pair)[0], pair, entered[pair]))

        enter(sorted(self.pairs))
        while queue:
            _, pair, number = heapq.heappop(queue)
            if number != entered[pair] or key(todo := self.candidate(pair)) in tried:
                continue
            tried.add(key(todo))
            _, c1, c2, border = todo
            both = sorted([*self.clusters[c1].members, *self.clusters[c2].members])
            out = self.next
            self.next += 1
            best = None
            for part, to in ((both, c1), (border, c1), (border, c2), (border, out)):
                moves = [(e, to) for e in part if self.of[e] != to]
                gain, valid, back = self.change(moves)
                self.undo(*back)
                if valid and gain > self.least and (best is None or gain > best[0] + self.least):
                    best = gain, moves
            if best:
                stamps = self.changes
                touched = self.file(self.settle(self.change(best[1])[2][2]))
                # a pair is tried again if its border elements, or one of its clusters, are not what they were
                enter(sorted(touched.union(*(self.paired.get(c, ()) for c, n in self.stamps.items() if n > stamps))))


def cluster_block(elements: list[Element], s: Settings, outside: frozenset = frozenset()) -> dict:
    """eid -> smallest eid of its cluster."""
    b = Block(elements, s, outside)
    b.initialise()
    if s.adjust:
        b.adjust()
    low: dict = {}
    for eid, c in b.of.items():
        low[c] = min(low.get(c, eid), eid)
    return {eid: low[c] for eid, c in b.of.items()}
