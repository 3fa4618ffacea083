"""Robust cores of one component, in memory: screening by clique unions, exact vertex cuts, a work queue.

A graph is a list of cliques (frozensets of nodes) with a record weight per node; edges are never listed. Overlap tests
use at least k+1 and at most k; a border counts as a separator only if it leaves something of its union and of
the rest. Border nodes found in one scan go at once. The strategies give equal cores by different work, except
``screen_only``, which never cuts.
"""

from __future__ import annotations

from collections import defaultdict, deque
from itertools import combinations

STRATEGIES = {"naive": (False, False, False), "index": (False, False, False), "sindex": (True, False, False), "union": (True, True, False), "full": (True, True, True), "screen_only": (True, True, True)}


def normalise(cliques, nodes=None) -> list[frozenset]:
    """Cliques cut to ``nodes``, without those contained in others."""
    out: list[frozenset] = []
    for c in sorted({frozenset(c if nodes is None else c & nodes) for c in cliques}, key=lambda c: (-len(c), sorted(c))):
        if c and not any(c <= d for d in out):
            out.append(c)
    return out


def pieces(nodes: set, cliques: list[frozenset]) -> list[set]:
    """Connected components of the nodes under the cliques."""
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for c in cliques:
        inside = [n for n in c if n in root]
        for n in inside[1:]:
            root[find(n)] = find(inside[0])
    out = defaultdict(set)
    for n in nodes:
        out[find(n)].add(n)
    return sorted(out.values(), key=min)


def unions(cliques: list[frozenset], k: int, closure: str = "clique") -> list[set]:
    """Unions of cliques that are linked by overlaps of k+1 nodes or more; ``closure='union'`` also merges on summed overlap."""
    at = defaultdict(list)
    for i, c in enumerate(cliques):
        for n in c:
            at[n].append(i)
    shared = defaultdict(int)
    for ids in at.values():
        for p in combinations(ids, 2):
            shared[p] += 1
    root = list(range(len(cliques)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for (i, j), n in shared.items():
        if n > k:
            root[find(j)] = find(i)
    out = defaultdict(set)
    for i, c in enumerate(cliques):
        out[find(i)] |= c
    found = list(out.values())
    while closure == "union":
        hit = next(((a, b) for a, b in combinations(range(len(found)), 2) if len(found[a] & found[b]) > k), None)
        if hit is None:
            break
        found[hit[0]] |= found.pop(hit[1])
    return found


def violating(found: list[set], nodes: set, k: int, guard: bool = True) -> set:
    """Nodes of all borders of at most k nodes."""
    count = defaultdict(int)
    for u in found:
        for n in u:
            count[n] += 1
    gone = set()
    for u in found:
        border = {n for n in u if count[n] > 1}
        if border and len(border) <= k and (not guard or (u - border and nodes - u)):
            gone |= border
    return gone


def min_cut(cliques: list[frozenset], weight: dict, a, b, cap: int) -> set | None:
    """A vertex cut between a and b of weight at most ``cap``, or None. Flow runs record, clique hub, record: linear in incidence."""
    near, far = (set().union(*(c for c in cliques if x in c)) for x in (a, b))
    # every cut holds the common neighbours
    if b in near or sum(weight[n] for n in near & far) > cap:
        return None
    res: dict = defaultdict(lambda: defaultdict(int))
    big = 1 << 60
    for n in {n for c in cliques for n in c}:
        res[(n, 0)][(n, 1)] = big if n in (a, b) else weight[n]
        res[(n, 1)][(n, 0)] += 0
    for i, c in enumerate(cliques):
        for n in c:
            res[(n, 1)][("hub", i)] = big
            res[("hub", i)][(n, 1)] += 0
            res[("hub", i)][(n, 0)] = big
            res[(n, 0)][("hub", i)] += 0
    flow = 0
    while True:
        seen, todo = {(a, 1): None}, deque([(a, 1)])
        while todo and (b, 0) not in seen:
            u = todo.popleft()
            for v, r in res[u].items():
                if r > 0 and v not in seen:
                    seen[v] = u
                    todo.append(v)
        if (b, 0) not in seen:
            return {n for n in {n for c in cliques for n in c} if (n, 0) in seen and (n, 1) not in seen}
        path, v = [], (b, 0)
        while seen[v] is not None:
            path.append((seen[v], v))
            v = seen[v]
        step = min(res[u][v] for u, v in path)
        flow += step
        if flow > cap:
            return None
        for u, v in path:
            res[u][v] -= step
            res[v][u] += step


def vertex_connectivity(cliques, weight: dict, a, b) -> int:
    """Least weight of nodes that part a from b (no clique may hold both)."""
    cut = min_cut([frozenset(c) for c in cliques], weight, a, b, 1 << 40)
    return sum(weight[n] for n in cut)


def find_cut(found: list[set], cliques: list[frozenset], weight: dict, k: int) -> set | None:
    """A separator of at most k records by one witness pair per pair of adjacent unions, or None."""
    apart: set = set()  # witness pairs that several pairs of unions may have
    for q, r in combinations(sorted(found, key=lambda u: sorted(u)), 2):
        if not q & r or q <= r or r <= q:
            continue
        a, b = min(q - r), min(r - q)
        if (a, b) in apart or (b, a) in apart:
            continue
        apart.add((a, b))
        cut = min_cut(cliques, weight, a, b, k)
        if cut is not None:
            return cut
    return None


def solve(cliques, weight: dict, k: int = 2, strategy: str = "full", guard: bool = True, closure: str = "clique", metrics: dict | None = None) -> list[set]:
    """Cores (sets of nodes) of a graph; a core stands for two records at least and holds no separator."""
    simple, use_unions, use_borders = STRATEGIES[strategy]
    m = metrics if metrics is not None else {}
    m.update({x: m.get(x, 0) for x in ("screens", "splits", "largest_screen", "largest_split")})
    cliques = normalise(cliques)
    if strategy == "naive":
        cliques = [frozenset(e) for c in cliques for e in combinations(sorted(c), 2)]
    every = set().union(*cliques) if cliques else set()
    todo, cores = [(p, frozenset()) for p in pieces(every, cliques)], []
    while todo:
        nodes, seps = todo.pop()
        own = normalise(cliques, nodes) if strategy != "naive" else [c for c in cliques if c <= nodes]
        if strategy == "naive" and len(nodes) == 1:
            own = [frozenset(nodes)]
        parts = pieces(nodes, own)
        if len(parts) > 1:
            todo += [(p, seps & p) for p in parts]
            continue
        strip = nodes & seps
        if k == 0 or len(own) == 1:
            if strip:
                todo.append((nodes - strip, frozenset())) if nodes - strip else None
            elif sum(weight[n] for n in nodes) > 1:
                cores.append(nodes)
            continue
        m["screens"] += 1
        m["largest_screen"] = max(m["largest_screen"], len(nodes))
        found = unions(own, k, closure) if use_unions else [set(c) for c in own]
        if len(found) > 1 and use_borders:
            gone = violating(found, nodes, k, guard)
            if gone:
                rest = nodes - gone
                todo += [(p, seps & p) for p in pieces(rest, normalise(own, rest))]
                continue
        if strip:
            rest = nodes - strip
            todo += [(p, frozenset()) for p in pieces(rest, normalise(own, rest))] if rest else []
            continue
        cut = None
        if len(found) > 1 and strategy != "screen_only":
            m["splits"] += 1
            m["largest_split"] = max(m["largest_split"], len(nodes))
            cut = find_cut(found, own, weight, k)
        if cut is None:
            if sum(weight[n] for n in nodes) > 1:
                cores.append(nodes)
            continue
        rest = nodes - cut
        for p in pieces(rest, [c - cut for c in own if c - cut]):
            side = p | cut
            todo.append((side, (seps & side) | cut))
    return sorted(cores, key=min)


def is_robust(cliques, k: int) -> bool:
    """By definition: every removal of up to k nodes leaves it connected; cliques and single nodes always are."""
    cliques = [frozenset(c) for c in cliques]
    nodes = set().union(*cliques)
    if any(nodes <= c for c in cliques):
        return True
    return all(len(pieces(nodes - set(gone), [c - set(gone) for c in cliques if c - set(gone)])) == 1 for n in range(k + 1) for gone in combinations(sorted(nodes), n) if nodes - set(gone))


def partitionings(nodes: list) -> list[list[frozenset]]:
    """All ways to part a few nodes."""
    if not nodes:
        return [[]]
    first, out = nodes[0], []
    for rest in partitionings(nodes[1:]):
        out += [[frozenset({first}), *rest], *([*rest[:i], rest[i] | {first}, *rest[i + 1 :]] for i in range(len(rest)))]
    return out


def maximal_partitionings(cliques, k: int) -> list[list[frozenset]]:
    """By definition, for graphs of up to eight nodes: parts are robust, and no union of several parts is."""
    cliques = [frozenset(c) for c in cliques]
    nodes = sorted(set().union(*cliques))
    if len(nodes) > 8:
        raise ValueError("the definition is tried on up to eight nodes")
    known: dict = {}

    def robust(part: frozenset) -> bool:
        if part not in known:
            known[part] = is_robust([c & part for c in cliques if c & part] + [{n} for n in part], k)
        return known[part]

    return [p for p in partitionings(nodes) if all(map(robust, p)) and not any(robust(frozenset().union(*some)) for n in range(2, len(p) + 1) for some in combinations(p, n))]


def definitional_cores(cliques, k: int) -> list[set]:
    """Nodes, two at least, that lie in one part in every maximal robust partitioning."""
    found = maximal_partitionings(cliques, k)
    together: dict = defaultdict(set)
    for n in set().union(*cliques):
        together[tuple(next(i for i, part in enumerate(p) if n in part) for p in found)].add(n)
    return sorted((c for c in together.values() if len(c) > 1), key=min)
