"""Sequential kernels on the arrays of one bounded group: the only row-at-a-time code.

Edges are parallel sequences u, v, w and edge_id.  The order of processing is
(|w| descending, u, v, edge_id).  Clusters are named by their least vertex.
"""

from __future__ import annotations

import heapq
from collections import defaultdict, deque
from dataclasses import dataclass, field

import numpy as np


def priority(u, v, w, edge_id) -> np.ndarray:
    """Row numbers in processing order."""
    return np.lexsort((np.asarray(edge_id), np.asarray(v), np.asarray(u), -np.abs(np.asarray(w, dtype=float))))


class Forest:
    """Union-find with path halving; the kept root carries whatever the caller stores for it."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        up = self.up
        if x not in up:
            up[x] = x
            return x
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def labels(self, vertices) -> dict[int, int]:
        """Least vertex of each vertex's cluster."""
        least: dict[int, int] = {}
        roots = {int(x): self.find(int(x)) for x in vertices}
        for x, r in roots.items():
            if x < least.get(r, x + 1):
                least[r] = x
        return {x: least[r] for x, r in roots.items()}


@dataclass
class Outcome:
    """Labels, one decision for each edge (in input order), exclusions by label, and counters."""

    labels: dict[int, int]
    decisions: list[str]
    exclusions: set[tuple[int, int]]
    counters: dict[str, int] = field(default_factory=dict)


#: What can happen to an edge.
MERGE, INSIDE, BLOCKED, EXCLUDE, REPEAT, IGNORED = "merge", "joined", "blocked", "exclude", "repeat", "ignored"
ACTIVE = {"tree": {MERGE, EXCLUDE, REPEAT}, "full": {MERGE, INSIDE, EXCLUDE, REPEAT}}


class Greedy:
    """The signed greedy partition of one group, fed with edges in processing order.

    A cluster's exclusions are a set of cluster roots, so the test is one look-up;
    the smaller set moves in a merge.  Holds clusters and exclusions, no edges.
    """

    def __init__(self) -> None:
        self.forest = Forest()
        self.apart: dict[int, set[int]] = {}
        self.count = dict.fromkeys((MERGE, INSIDE, BLOCKED, EXCLUDE, REPEAT, IGNORED, "probes", "moved"), 0)

    def join(self, a: int, b: int) -> None:
        apart = self.apart
        sa, sb = apart.get(a), apart.get(b)
        if (len(sa) if sa else 0) < (len(sb) if sb else 0):
            a, b, sa, sb = b, a, sb, sa
        self.forest.up[b] = a
        if sb:
            for c in sb:
                sc = apart[c]
                sc.discard(b)
                sc.add(a)
            sa |= sb
            self.count["moved"] += len(sb)
            del apart[b]

    def take(self, us: list[int], vs: list[int], ws: list[float]) -> list[str]:
        """The decisions on the next edges."""
        find, apart, count, join = self.forest.find, self.apart, self.count, self.join
        decisions = []
        for x, y, weight in zip(us, vs, ws):
            a, b = find(x), find(y)
            if weight > 0:
                if a == b:
                    d = INSIDE
                else:
                    sa, sb = apart.get(a), apart.get(b)
                    count["probes"] += 1
                    if sa and sb and b in sa:
                        d = BLOCKED
                    else:
                        join(a, b)
                        d = MERGE
            elif a == b:
                d = IGNORED
            else:
                sa = apart.setdefault(a, set())
                if b in sa:
                    d = REPEAT
                else:
                    sa.add(b)
                    apart.setdefault(b, set()).add(a)
                    d = EXCLUDE
            count[d] += 1
            decisions.append(d)
        return decisions


def greedy(u, v, w, edge_id, vertices=None, start_links=(), start_exclusions=()) -> Outcome:
    """The signed greedy partition of one group.

    start_links are pairs already joined, start_exclusions pairs already kept apart.
    """
    run = Greedy()
    find, up, apart = run.forest.find, run.forest.up, run.apart
    for a, b in start_links:
        ra, rb = find(int(a)), find(int(b))
        if ra != rb:
            run.join(ra, rb)
    for a, b in start_exclusions:
        ra, rb = find(int(a)), find(int(b))
        if ra == rb:
            raise ValueError("the given active set joins two clusters that it keeps apart")
        apart.setdefault(ra, set()).add(rb)
        apart.setdefault(rb, set()).add(ra)

    us, vs, ws, order = np.asarray(u), np.asarray(v), np.asarray(w, dtype=float), priority(u, v, w, edge_id)
    decisions = [IGNORED] * len(us)
    for k, d in zip(order.tolist(), run.take(us[order].tolist(), vs[order].tolist(), ws[order].tolist())):
        decisions[k] = d
    known = set(us.tolist()) | set(vs.tolist()) | ({int(x) for x in vertices} if vertices is not None else set()) | set(up)
    labels = run.forest.labels(known)
    pairs = {(min(labels[a], labels[b]), max(labels[a], labels[b])) for a, s in apart.items() for b in s}
    return Outcome(labels, decisions, pairs, run.count)


def seeded(u, v, w, edge_id, seeds: dict[int, int], vertices=None) -> Outcome:
    """Flood from seeds over attractive edges: clusters with different seeds never join."""
    forest = Forest()
    mark = {int(x): s for x, s in seeds.items()}
    decisions = [IGNORED] * len(u)
    us, vs, ws = np.asarray(u).tolist(), np.asarray(v).tolist(), np.asarray(w, dtype=float).tolist()
    # Seeds of one label start joined.
    by_label: dict[int, int] = {}
    for x, s in sorted(mark.items()):
        first = by_label.setdefault(s, x)
        a, b = forest.find(first), forest.find(x)
        if a != b:
            forest.up[b] = a
    root_mark = {forest.find(x): s for x, s in mark.items()}
    for k in priority(u, v, w, edge_id).tolist():
        if ws[k] <= 0:
            continue
        a, b = forest.find(us[k]), forest.find(vs[k])
        if a == b:
            decisions[k] = INSIDE
        elif a in root_mark and b in root_mark:
            decisions[k] = BLOCKED
        else:
            forest.up[b] = a
            if b in root_mark:
                root_mark[a] = root_mark.pop(b)
            decisions[k] = MERGE
    known = set(us) | set(vs) | ({int(x) for x in vertices} if vertices is not None else set()) | set(mark)
    return Outcome(forest.labels(known), decisions, set())


def spanning_forest(u, v, w, edge_id) -> np.ndarray:
    """Whether each edge is in the maximum spanning forest of all given edges (by w, then the total order)."""
    forest, keep = Forest(), np.zeros(len(u), dtype=bool)
    order = np.lexsort((np.asarray(edge_id), np.asarray(v), np.asarray(u), -np.asarray(w, dtype=float)))
    us, vs = np.asarray(u).tolist(), np.asarray(v).tolist()
    for k in order.tolist():
        a, b = forest.find(us[k]), forest.find(vs[k])
        if a != b:
            forest.up[b] = a
            keep[k] = True
    return keep


def _least_members(up: list[int]) -> list[int]:
    """The least member of each vertex's cluster, of a union-find over 0 … n-1 whose links go anywhere."""
    n, least = len(up), list(range(len(up)))
    roots = [0] * n
    for x in range(n):
        r = x
        while up[r] != r:
            up[r] = up[up[r]]
            r = up[r]
        roots[x] = r
        if x < least[r]:
            least[r] = x
    return [least[r] for r in roots]


def greedy_within(n: int, us: list[int], vs: list[int], attracts: list[bool], start_exclusions=(), excluded_outside=()) -> tuple[list[int], list[int], set[tuple[int, int]]]:
    """What a part of a graph settles by itself: (least member of each vertex's cluster, places of the open edges, exclusions).

    Vertices are 0 … n-1, edges come in processing order, and v = -1 is an end in
    another part.  From an edge that isn't settled here, its clusters here are
    *open*: they may hold more vertices, or be kept from more clusters, than is known
    here.  Two vertices in different clusters are surely apart if one cluster isn't
    open; an open cluster surely takes one that isn't and that nothing open is kept
    from.  All else waits, so what is settled is what the whole graph decides.
    Exclusions are given between open clusters only; no other can matter later.
    """
    up, opened, held = list(range(n)), bytearray(n), bytearray(n)
    apart: dict[int, set[int]] = {}
    waiting: list[int] = []
    for a, b in start_exclusions:
        apart.setdefault(a, set()).add(b)
        apart.setdefault(b, set()).add(a)
    for a in excluded_outside:
        held[a] = 1
    for k, (a, b, attract) in enumerate(zip(us, vs, attracts)):
        while up[a] != a:
            up[a] = a = up[up[a]]
        if b < 0:
            opened[a] = 1
            waiting.append(k)
            continue
        while up[b] != b:
            up[b] = b = up[up[b]]
        if a == b:
            continue
        sa = apart.get(a)
        if sa and b in sa:
            continue
        if opened[a] and opened[b]:
            waiting.append(k)
            continue
        sb = apart.get(b)
        if not attract:
            if sa is None:
                sa = apart[a] = set()
            if sb is None:
                sb = apart[b] = set()
            sa.add(b)
            sb.add(a)
            continue
        if opened[a] or opened[b]:
            closed, sc = (b, sb) if opened[a] else (a, sa)
            if held[closed] or (sc and any(opened[c] for c in sc)):
                opened[closed] = 1
                waiting.append(k)
                continue
        if (len(sa) if sa else 0) < (len(sb) if sb else 0):
            a, b, sa, sb = b, a, sb, sa
        up[b] = a
        opened[a] |= opened[b]
        held[a] |= held[b]
        if sb:
            for c in sb:
                sc = apart[c]
                sc.discard(b)
                sc.add(a)
            sa |= sb
            del apart[b]
    least = _least_members(up)
    pairs = {(min(least[a], least[c]), max(least[a], least[c])) for a, s in apart.items() if opened[a] for c in s if opened[c]}
    return least, waiting, pairs


def flood_within(n: int, us: list[int], vs: list[int], seeds: list[int]) -> tuple[list[int], list[int]]:
    """The same for a flood from seeds (-1: none) over attractions: (least member of each vertex's cluster, places of the open edges).

    A cluster with a seed has it for good, so only clusters without one are open.
    """
    up, opened, mark = list(range(n)), bytearray(n), list(seeds)
    first: dict[int, int] = {}
    for x, s in enumerate(mark):
        if s >= 0:
            up[x] = first.setdefault(s, x)
    waiting: list[int] = []
    for k, (a, b) in enumerate(zip(us, vs)):
        while up[a] != a:
            up[a] = a = up[up[a]]
        if b < 0:
            opened[a] = 1
            waiting.append(k)
            continue
        while up[b] != b:
            up[b] = b = up[up[b]]
        if a == b:
            continue
        ma, mb = mark[a] >= 0, mark[b] >= 0
        if ma and mb:
            continue
        if (ma or opened[a]) and (mb or opened[b]):
            waiting.append(k)
            continue
        up[b] = a
        opened[a] |= opened[b]
        if mb:
            mark[a] = mark[b]
    return _least_members(up), waiting


def greedy_by_cycles(u, v, w, edge_id) -> list[bool]:
    """Accepts an edge unless it would close a cycle with exactly one repulsive edge.

    Tests by searching paths in what was accepted, without clusters or exclusion
    sets, so that it can stand against the main kernel.
    """
    attract: dict[int, list[int]] = defaultdict(list)
    repel: list[tuple[int, int]] = []
    taken = [False] * len(u)

    def reach(a: int) -> set[int]:
        seen, queue = {a}, deque([a])
        while queue:
            for y in attract[queue.popleft()]:
                if y not in seen:
                    seen.add(y)
                    queue.append(y)
        return seen

    for k in priority(u, v, w, edge_id).tolist():
        a, b = int(u[k]), int(v[k])
        here = reach(a)
        if w[k] < 0:
            bad = b in here
        else:
            there = reach(b)
            bad = any((p in here and q in there) or (q in here and p in there) for p, q in repel) and b not in here
        if bad:
            continue
        taken[k] = True
        if w[k] > 0:
            attract[a].append(b)
            attract[b].append(a)
        else:
            repel.append((a, b))
    return taken


def contraction(u, v, w, vertices=None, by_size: bool = False) -> dict[int, int]:
    """Greedy additive contraction; with ``by_size`` its variant that also fixes repulsive pairs.

    Parallel costs add up when clusters merge.  The first form merges the pair of
    the largest sum while that is positive; the second takes the largest absolute
    sum and turns a negative one into a lasting cannot-link.
    """
    near: dict[int, dict[int, float]] = defaultdict(dict)
    fixed: dict[int, set[int]] = defaultdict(set)
    for a, b, c in zip(np.asarray(u).tolist(), np.asarray(v).tolist(), np.asarray(w, dtype=float).tolist()):
        near[a][b] = near[b][a] = near[a].get(b, 0.0) + c
    if vertices is not None:
        for x in vertices:
            near[int(x)]
    forest = Forest()
    rank = abs if by_size else (lambda c: c)
    heap = [(-rank(c), a, b, c) for a, ns in near.items() for b, c in ns.items() if a < b]
    heapq.heapify(heap)
    while heap:
        score, a, b, c = heapq.heappop(heap)
        if near.get(a, {}).get(b) != c:
            continue
        if not by_size and c <= 0:
            break
        if c <= 0:
            if b not in fixed[a]:
                fixed[a].add(b)
                fixed[b].add(a)
            continue
        if b in fixed[a]:
            continue
        forest.find(a), forest.find(b)
        forest.up[b] = a  # a < b, so the root is the least vertex
        for x, cost in near.pop(b).items():
            near[x].pop(b, None)
            if x == a:
                continue
            total = near[a].get(x, 0.0) + cost
            near[a][x] = near[x][a] = total
            if b in fixed[x]:
                fixed[x].add(a)
                fixed[a].add(x)
            lo, hi = (a, x) if a < x else (x, a)
            heapq.heappush(heap, (-rank(total), lo, hi, total))
        near[a].pop(b, None)
    return forest.labels(set(np.asarray(u).tolist()) | set(np.asarray(v).tolist()) | ({int(x) for x in vertices} if vertices is not None else set()))


#: Fixed value: costs are multiples of this, so that doubles hold their sums exactly and no order of adding up matters.
GRAIN = 2.0**-30


def contraction_within(n: int, us: list[int], vs: list[int], ws: list[float], outside: list[bool], least: float = 0.0) -> tuple[list[int], list[bool], dict[int, dict[int, float]]]:
    """What a part of a graph settles of its greedy additive contraction: (least member of each vertex's cluster, open clusters, costs between clusters).

    Vertices are 0 … n-1, and those ``outside`` are another part's.  A cluster is
    *open* from the moment at which the rest of the graph may have changed it: what
    is open may join to anything, so a cluster can be taken at any score up to the
    sum of its positive costs to open ones.  That moment is an entry of the heap
    like any other.  Two clusters that aren't open join as in the whole graph, and
    one that isn't open in the end is final.
    """
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for a, b, c in zip(us, vs, ws):
        near[a][b] = near[b][a] = near[a].get(b, 0.0) + c
    up, opened, risk = list(range(n)), list(outside), [0.0] * n
    heap: list[tuple[float, int, int]] = []
    for a, ns in enumerate(near):
        if opened[a]:
            continue
        for b, c in ns.items():
            if c > 0:
                if opened[b]:
                    risk[a] += c
                elif a < b:
                    heap.append((-c, a, b))
        if risk[a] > 0:
            heap.append((-risk[a], -1, a))
    heapq.heapify(heap)
    pop, push = heapq.heappop, heapq.heappush
    while heap:
        score, a, b = pop(heap)
        if -score <= least:
            break
        if a < 0:
            if up[b] == b and not opened[b] and risk[b] == -score:
                opened[b] = True
                for x, c in near[b].items():
                    if c > 0 and not opened[x]:
                        risk[x] += c
                        push(heap, (-risk[x], -1, x))
            continue
        if up[a] != a or up[b] != b or opened[a] or opened[b] or near[a].get(b) != -score:
            continue
        up[b] = a
        na, nb = near[a], near[b]
        near[b] = {}
        del na[b], nb[a]
        total_risk = risk[a] + risk[b]
        for x, cost in nb.items():
            nx = near[x]
            del nx[b]
            old = na.get(x)
            total = cost if old is None else old + cost
            na[x] = nx[a] = total
            if opened[x]:
                if old is not None:
                    total_risk += (total if total > 0 else 0.0) - (old if old > 0 else 0.0) - (cost if cost > 0 else 0.0)
            elif total > 0:
                push(heap, (-total, a, x) if a < x else (-total, x, a))
        if total_risk != risk[a]:
            risk[a] = total_risk
            if total_risk > 0:
                push(heap, (-total_risk, -1, a))
    return _least_members(up), opened, {a: near[a] for a in range(n) if up[a] == a and opened[a] and not outside[a]}


def cut_cost(u, v, w, labels: dict[int, int]) -> float:
    """Sum of the weights between clusters: the multicut cost up to a constant."""
    return float(sum(c for a, b, c in zip(u, v, w) if labels[int(a)] != labels[int(b)]))


#: Vertices of a chain that are looked at one by one.
FEW = 16


class _Side:
    """The vertices on one side of a chain, and whether local edges hold them together, without a search for each move.

    No local edge ties ``apart`` to the rest.  If the rest isn't connected, each part
    of it has one of ``ends`` (None: not known).
    """

    def __init__(self, members, linked: list[set[int]]) -> None:
        self.members, self.linked, self.apart, self.ends = set(members), linked, set(), None

    def add(self, x: int) -> None:
        members, apart, linked = self.members, self.apart, self.linked
        beside = [y for y in linked[x] if y in members]
        held = [y for y in beside if y in apart]
        if members and len(held) == len(beside):
            apart.add(x)
        else:
            # x ties these to the rest.
            while held:
                y = held.pop()
                if y in apart:
                    apart.discard(y)
                    held.extend(z for z in linked[y] if z in apart)
        members.add(x)

    def remove(self, x: int) -> None:
        self.members.discard(x)
        if x in self.apart:
            self.apart.discard(x)
        elif self.ends is not None:
            self.ends.extend(y for y in self.linked[x] if y in self.members)

    def connected(self) -> bool:
        members = self.members
        if len(members) < 2:
            return True
        if len(self.apart) == len(members):
            self.apart, self.ends = set(), None
        if self.apart:
            return False
        if self.ends is None:
            first = next(iter(members))
            seen, queue = {first}, [first]
            while queue:
                for y in self.linked[queue.pop()]:
                    if y in members and y not in seen:
                        seen.add(y)
                        queue.append(y)
            self.apart, self.ends = members - seen, []
            return not self.apart
        return self._meet()

    def _meet(self) -> bool:
        """Searches from all ends in turn, until they have met or one has nowhere to go."""
        members, linked = self.members, self.linked
        starts = list(dict.fromkeys(y for y in self.ends if y in members))
        of, up = {y: i for i, y in enumerate(starts)}, list(range(len(starts)))
        todo, seen, turns, left = [deque([y]) for y in starts], [[y] for y in starts], deque(up), len(starts)
        while left > 1:
            i = turns.popleft()
            if up[i] != i:
                continue
            if not todo[i]:
                self.apart = set(seen[i])
                self.ends = [y for y in starts if y not in self.apart]
                return False
            for z in linked[todo[i].popleft()]:
                if z not in members:
                    continue
                j = of.get(z)
                if j is None:
                    of[z] = i
                    todo[i].append(z)
                    seen[i].append(z)
                    continue
                while up[j] != j:
                    up[j] = j = up[up[j]]
                if j != i:
                    if len(seen[j]) > len(seen[i]):
                        todo[i], todo[j], seen[i], seen[j] = todo[j], todo[i], seen[j], seen[i]
                    todo[i].extend(todo[j])
                    seen[i].extend(seen[j])
                    up[j] = i
                    left -= 1
            turns.append(i)
        self.ends = []
        return True


def moves(u, v, w, labels: dict[int, int], local=None, most_rounds: int = 50, tried: tuple = ((), ())) -> dict[int, int]:
    """Improves a multicut by sequences of vertex moves and by joining clusters; never raises the cost.

    For each pair of neighbouring clusters the best single moves are chained, each
    vertex once, and the prefix with the largest gain is kept; a cluster may also
    split into itself and a new one, and a pair may join.  ``local`` (a flag for
    each edge) makes it the lifted form: edges that are not local count in the
    gains, and only steps that leave clusters connected by local edges are taken.
    ``tried`` are pairs of clusters, and clusters to split, known to give nothing.
    """
    lab = {int(x): int(c) for x, c in labels.items()}
    names = sorted(lab)
    at = {x: k for k, x in enumerate(names)}
    us, vs, ws = [at[int(x)] for x in u], [at[int(x)] for x in v], [float(x) for x in w]
    costs: list[dict[int, float]] = [{} for _ in names]
    linked: list[set[int]] = [set() for _ in names]
    for k, (a, b, c) in enumerate(zip(us, vs, ws)):
        costs[a][b] = costs[b][a] = costs[a].get(b, 0.0) + c
        if local is None or local[k]:
            linked[a].add(b)
            linked[b].add(a)
    # Vertices are places in ``names`` from here on; a move changes a neighbour's gain by twice their cost.
    near = [[(y, 2 * c) for y, c in ns.items()] for ns in costs]
    fresh = max(names, default=0) + 1
    lab = [lab[x] for x in names]
    members: dict[int, set[int]] = defaultdict(set)
    for x, c in enumerate(lab):
        members[c].add(x)
    lifted = local is not None
    tiny = 1e-9
    gains, side = [0.0] * len(names), bytearray(len(names))
    inner: dict[int, tuple[int, dict[int, float], float]] = {}

    def pull(x: int, cluster: set[int]) -> float:
        return sum(c for y, c in costs[x].items() if y in cluster)

    def pulls(p: int) -> dict[int, float]:
        """What its own cluster p pulls each vertex with; reckoned anew when p has changed."""
        known = inner.get(p)
        if known is None or known[0] != version[p]:
            own = {x: pull(x, members[p]) for x in members[p]}
            inner[p] = known = version[p], own, min(own.values())
        return known[1]

    def hopeless(p: int, q: int, cross: dict[int, float]) -> bool:
        """Whether no single move between p and q gains, so that a chain has no first step; ``cross`` is what the other cluster pulls with."""
        own_p, own_q = pulls(p), pulls(q)
        if inner[p][2] < 0 or inner[q][2] < 0:
            return False
        return all(c <= (own_p[x] if lab[x] == p else own_q[x]) for x, c in cross.items())

    def chain(p: int, q: int | None) -> tuple[float, list[tuple[int, bool]]]:
        """The best prefix of single moves between p and q, or p and a new cluster."""
        both = {1: members[p]} if q is None else {1: members[p], 2: members[q]}
        for k, c in zip(both, (p, q)):
            for x, own in pulls(c).items():
                gains[x], side[x] = -own, k
        if q is not None:
            few, many = sorted(both.values(), key=len)
            for x in {y for x in few for y in costs[x] if y in many}:
                gains[x] += pull(x, few)
            for x in few:
                gains[x] += pull(x, many)
        # ``side`` marks those that may still move; an entry of each isn't below its gain, and is made anew when it comes first.
        queue = [(-gains[x], x) for c in both.values() for x in c]
        heapq.heapify(queue)
        scan = len(queue) <= FEW

        def first() -> int | None:
            """Which vertex moves next: among few by a look at all, else by the queue."""
            if scan:
                free = {names[x]: gains[x] for c in both.values() for x in c if side[x]}
                return at[min(free, key=lambda y: (-free[y], y))] if free else None
            while queue:
                g, x = queue[0]
                if not side[x] or gains[x] > -g:
                    heapq.heappop(queue)
                elif gains[x] < -g:
                    heapq.heapreplace(queue, (-gains[x], x))
                else:
                    return x
            return None

        rising = [-g for g, _ in queue if g < 0]
        n_rising, rise, top = len(rising), sum(rising), sum(rising)
        a, b = (_Side(both.get(k, ()), linked) for k in (1, 2)) if lifted else (None, None)
        total, best, steps, kept = 0.0, 0.0, [], 0
        while (x := first()) is not None:
            gain = gains[x]
            if not n_rising:
                rise = 0.0
            elif total + gain + rise <= best + tiny + 1e-6 * (1 + top):
                rise = sum(gains[y] for c in both.values() for y in c if side[y] and gains[y] > 0)
            if total + gain + rise <= best + tiny:
                break
            mine, side[x] = side[x], 0
            if gain > 0:
                n_rising -= 1
                rise -= gain
            total += gain
            for y, c in near[x]:
                if s := side[y]:
                    old = gains[y]
                    gains[y] = now = old + c if s == mine else old - c
                    if now > old and not scan:
                        heapq.heappush(queue, (-now, y))
                    if now > 0:
                        if old > 0:
                            rise += now - old
                        else:
                            n_rising += 1
                            rise += now
                    elif old > 0:
                        n_rising -= 1
                        rise -= old
            if rise > top:
                top = rise
            steps.append((x, mine == 1))
            if lifted:
                out, into = (a, b) if mine == 1 else (b, a)
                out.remove(x)
                into.add(x)
            if total > best + tiny and (not lifted or all(s.connected() for s in sorted((a, b), key=lambda s: len(s.members)))):
                best, kept = total, len(steps)
        for c in both.values():
            for x in c:
                side[x] = 0
        return best, steps[:kept]

    # What a pair of clusters, or a cluster and a new one, gives follows from their members alone,
    # so a pair that gave nothing isn't tried again before one of them changes.
    version: dict[int, int] = defaultdict(int)
    settled: dict[tuple[int, int], tuple[int, int]] = dict.fromkeys(tried[0], (0, 0))
    whole: dict[int, int] = dict.fromkeys(tried[1], 0)
    for _ in range(most_rounds):
        improved = False
        pairs = sorted({(min(lab[a], lab[b]), max(lab[a], lab[b])) for a, b in zip(us, vs) if lab[a] != lab[b]})
        for p, q in pairs:
            if not members.get(p) or not members.get(q):
                continue
            now = version[p], version[q]
            if settled.get((p, q)) == now:
                continue
            few, other = (members[p], q) if len(members[p]) <= len(members[q]) else (members[q], p)
            between, cross = 0.0, defaultdict(float)
            for x in few:
                for y, c in costs[x].items():
                    if lab[y] == other:
                        between += c
                        cross[x] += c
                        cross[y] += c
            # Among few vertices a chain is no longer than this look.
            gain, steps = (0.0, []) if len(members[p]) + len(members[q]) > FEW and hopeless(p, q, cross) else chain(p, q)
            if between > max(gain, 0) + tiny and (not lifted or _Side(members[p] | members[q], linked).connected()):
                for x in members.pop(q):
                    lab[x] = p
                    members[p].add(x)
                improved = True
            elif gain > tiny:
                for x, from_p in steps:
                    s, t = (p, q) if from_p else (q, p)
                    members[s].discard(x)
                    members[t].add(x)
                    lab[x] = t
                improved = True
            else:
                settled[p, q] = now
                continue
            version[p] += 1
            version[q] += 1
        for p in sorted(members):
            if len(members[p]) < 2 or whole.get(p) == version[p]:
                continue
            pulls(p)
            gain, steps = chain(p, None) if inner[p][2] < 0 else (0.0, [])
            if gain > tiny:
                for x, from_p in steps:
                    s, t = (p, fresh) if from_p else (fresh, p)
                    members[s].discard(x)
                    members[t].add(x)
                    lab[x] = t
                version[p] += 1
                fresh += 1
                improved = True
            else:
                whole[p] = version[p]
        if not improved:
            break
    least = {c: names[min(m)] for c, m in members.items() if m}
    return {x: least[c] for x, c in zip(names, lab)}


def partitions(n: int):
    """All set partitions of n items as label tuples in restricted growth."""
    if n == 0:
        yield ()
        return
    stack = [((0,), 0)]
    while stack:
        row, top = stack.pop()
        if len(row) == n:
            yield row
        else:
            stack.extend((row + (c,), max(top, c)) for c in range(top + 2))


def exact_levels(u, v, w, vertices, most: int = 10) -> dict[int, int]:
    """The labeling whose dropped edges are least, level by level from the largest |w|; ties to the first in order.

    Enumerates all partitions, so the group is bounded by ``most`` vertices.
    """
    names = sorted({int(x) for x in vertices} | {int(x) for x in u} | {int(x) for x in v})
    if len(names) > most:
        raise ValueError(f"exact levels are limited to {most} vertices")
    at = {x: i for i, x in enumerate(names)}
    sizes = sorted({abs(float(c)) for c in w}, reverse=True)
    level = {s: i for i, s in enumerate(sizes)}
    rows = [(at[int(a)], at[int(b)], c > 0, level[abs(float(c))]) for a, b, c in zip(u, v, w)]
    best, chosen = None, None
    for labels in partitions(len(names)):
        dropped = [0] * len(sizes)
        for a, b, attract, k in rows:
            dropped[k] += (labels[a] == labels[b]) != attract
        key = (dropped, labels)
        if best is None or key < best:
            best, chosen = key, labels
    least: dict[int, int] = {}
    for x in names:
        least.setdefault(chosen[at[x]], x)
    return {x: least[chosen[at[x]]] for x in names}


def least_joined(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least member of each vertex's component, of vertices 0 … n-1 joined by the pairs a, b; whole arrays at a time."""
    up = np.arange(n)
    while len(a):
        ra, rb = up[a], up[b]
        open_ = ra != rb
        a, b, ra, rb = a[open_], b[open_], ra[open_], rb[open_]
        np.minimum.at(up, np.maximum(ra, rb), np.minimum(ra, rb))
        while True:
            then = up[up]
            if np.array_equal(then, up):
                break
            up = then
    return up


def straight_distances(held: np.ndarray, far: int) -> np.ndarray:
    """Squared distance to the nearest 0 along the first axis, at most ``far``."""
    steps, run = np.full(held.shape, far, dtype=np.int64), np.full(held.shape[1], far, dtype=np.int64)
    for sweep in (range(len(held)), range(len(held) - 1, -1, -1)):
        run[:] = far
        for y in sweep:
            run = np.where(held[y] == 0, 0, np.minimum(run + 1, far))
            steps[y] = np.minimum(steps[y], run)
    return np.minimum(np.minimum(steps, len(held)) ** 2 + np.where(steps >= far, far, 0), far)


def squared_distances(held: np.ndarray, far: int) -> np.ndarray:
    """The least held value plus squared step along the first axis, at most ``far``; no step is tried that is too long for all."""
    best, n = np.minimum(held, far), len(held)
    for step in range(1, n):
        if step * step >= best.max(initial=0):
            break
        best[step:] = np.minimum(best[step:], held[:-step] + step * step)
        best[:-step] = np.minimum(best[:-step], held[step:] + step * step)
    return best


def distance_transform(mask: np.ndarray) -> np.ndarray:
    """Squared distance of each pixel to the nearest set pixel of a 2-D mask, exact; columns, then rows."""
    far = mask.shape[0] ** 2 + mask.shape[1] ** 2 + 1
    return squared_distances(straight_distances(np.where(mask, 0, far), far).T, far).T
