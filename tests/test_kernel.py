"""The kernels against each other, brute force and the worked example."""

import itertools
import random
from collections import Counter, defaultdict

import numpy as np
import pytest

from signpart import kernels, workloads
from tests.conftest import random_edges

U, V, W = zip(*workloads.EXAMPLE)


def columns(rows):
    u, v, w, channel = zip(*rows)
    return list(u), list(v), list(w), list(channel)


def lexicographic(rows, labels):
    """Dropped edges in processing order."""
    u, v, w, c = columns(rows)
    return [int((w[k] > 0) != (labels[u[k]] == labels[v[k]])) for k in kernels.priority(u, v, w, c)]


def test_worked_example():
    out = kernels.greedy(U, V, W, range(10))
    assert out.decisions == ["merge", "exclude", "merge", "blocked", "merge", "ignored", "merge", "joined", "blocked", "repeat"]
    assert out.labels == {0: 0, 1: 0, 5: 0, 2: 2, 3: 2, 4: 2}
    assert sum(abs(w) for u, v, w in workloads.EXAMPLE if (w > 0) != (out.labels[u] == out.labels[v])) == 29


@pytest.mark.parametrize("seed", range(60))
def test_greedy_is_the_lexicographic_optimum(seed):
    rows = random_edges(2 + seed % 5, 3 + seed % 9, seed)
    u, v, w, c = columns(rows)
    mine = kernels.greedy(u, v, w, c).labels
    names = sorted(mine)
    best = min(lexicographic(rows, dict(zip(names, p))) for p in kernels.partitions(len(names)))
    assert lexicographic(rows, mine) == best


@pytest.mark.parametrize("seed", range(40))
def test_cycle_form_accepts_the_same_edges(seed):
    u, v, w, c = columns(random_edges(8, 18, seed))
    out = kernels.greedy(u, v, w, c)
    assert kernels.greedy_by_cycles(u, v, w, c) == [d in kernels.ACTIVE["full"] for d in out.decisions]


@pytest.mark.parametrize("seed", range(20))
def test_only_order_and_signs_matter(seed):
    u, v, w, c = columns(random_edges(10, 25, seed))
    assert kernels.greedy(u, v, w, c).labels == kernels.greedy(u, v, [np.sign(x) * abs(x) ** 3 * 7 for x in w], c).labels


@pytest.mark.parametrize("seed", range(20))
def test_any_prefix_is_a_warm_start(seed):
    rows = random_edges(9, 24, seed)
    u, v, w, c = columns(rows)
    whole = kernels.greedy(u, v, w, c)
    order = kernels.priority(u, v, w, c)
    first, rest = order[:10], order[10:]
    start = kernels.greedy(*(np.take(x, first) for x in (u, v, w, c)))
    links = [(u[k], v[k]) for k, d in zip(first, start.decisions) if d == kernels.MERGE]
    apart = [(u[k], v[k]) for k, d in zip(first, start.decisions) if d == kernels.EXCLUDE]
    then = kernels.greedy(*(np.take(x, rest) for x in (u, v, w, c)), vertices=set(u) | set(v), start_links=links, start_exclusions=apart)
    assert then.labels == whole.labels


def test_positive_only_is_components_and_negative_only_is_singletons():
    u, v, w, c = columns(random_edges(12, 10, 3))
    joined = kernels.greedy(u, v, np.abs(w), c).labels
    apart = kernels.greedy(u, v, -np.abs(w), c).labels
    assert all(joined[a] == joined[b] for a, b in zip(u, v)) and all(k == x for k, x in apart.items())


def test_contradicting_start_raises():
    with pytest.raises(ValueError):
        kernels.greedy([0], [1], [1.0], [0], start_links=[(0, 1)], start_exclusions=[(0, 1)])


def test_empty_graph():
    assert kernels.greedy([], [], [], []).labels == {}
    assert kernels.greedy([], [], [], [], vertices=[4]).labels == {4: 4}


@pytest.mark.parametrize("seed", range(15))
def test_seeded_flood_keeps_seeds_apart(seed):
    u, v, w, c = columns(random_edges(10, 30, seed))
    labels = kernels.seeded(u, v, np.abs(w), c, {0: 0, 3: 1, 7: 2}).labels
    assert len({labels[0], labels[3], labels[7]}) == 3


@pytest.mark.parametrize("seed", range(15))
def test_levels_with_ties_are_at_least_as_good(seed):
    rows = random_edges(6, 12, seed, distinct=False)
    u, v, w, c = columns(rows)

    def per_level(labels):
        sizes = sorted({abs(x) for x in w}, reverse=True)
        return [sum((x > 0) != (labels[a] == labels[b]) for a, b, x in zip(u, v, w) if abs(x) == s) for s in sizes]

    exact = kernels.exact_levels(u, v, w, vertices=())
    assert per_level(exact) <= per_level(kernels.greedy(u, v, w, c).labels)


@pytest.mark.parametrize("seed", range(15))
def test_moves_never_cost_more_and_reach_the_optimum_or_stay_above(seed):
    rows = random_edges(7, 14, seed)
    u, v, w, _ = columns(rows)
    start = kernels.contraction(u, v, w)
    better = kernels.moves(u, v, w, start)
    names = sorted(better)
    least = min(kernels.cut_cost(u, v, w, dict(zip(names, p))) for p in kernels.partitions(len(names)))
    assert least <= kernels.cut_cost(u, v, w, better) <= kernels.cut_cost(u, v, w, start)


@pytest.mark.parametrize("seed", range(10))
def test_lifted_clusters_are_connected(seed):
    rows = random_edges(8, 20, seed)
    u, v, w, _ = columns(rows)
    local = [k % 2 == 0 for k in range(len(u))]
    near = [[x for x, keep in zip(col, local) if keep] for col in (u, v, w)]
    labels = kernels.moves(u, v, w, kernels.contraction(*near, vertices=set(u) | set(v)), local=local)
    parts = kernels.Forest()
    for a, b in zip(near[0], near[1]):
        if labels[a] == labels[b]:
            parts.up[parts.find(a)] = parts.find(b)
    for c in set(labels.values()):
        assert len({parts.find(x) for x in labels if labels[x] == c}) == 1


def test_distance_transform_equals_brute_force():
    rnd = np.random.default_rng(1)
    mask = rnd.random((9, 13)) < 0.1
    set_at = np.argwhere(mask)
    want = np.asarray([[min((y - a) ** 2 + (x - b) ** 2 for a, b in set_at) for x in range(13)] for y in range(9)])
    assert (kernels.distance_transform(mask) == want).all()


def test_partitions_are_counted_by_bell_numbers():
    assert [sum(1 for _ in kernels.partitions(n)) for n in range(1, 7)] == [1, 2, 5, 15, 52, 203]
    assert len(set(itertools.chain.from_iterable([list(kernels.partitions(5))]))) == 52


def test_probe_cost_streams_components(spark):
    """Counters of separate graphs add up to those of all edges in one kernel, and no task takes all edges as one group."""
    from signpart.operators import graph, partition

    rows = [(u + 100 * g, v + 100 * g, w, c) for g in range(5) for u, v, w, c in random_edges(14, 60, g, distinct=False)]
    edges = graph.build(spark.createDataFrame(rows, "u long, v long, w double, channel int")).cache()
    frame = edges.toPandas()
    want = kernels.greedy(frame["u"], frame["v"], frame["w"], frame["edge_id"]).counters
    for small in (3, 10_000):
        made = partition.probe_cost(edges, small)
        assert {r["counter"]: r["n"] for r in made.collect()} == want
        assert "FlatMapGroupsInPandas" not in made._jdf.queryExecution().toString()
    assert {r["n"] for r in partition.probe_cost(edges.limit(0)).collect()} == {0}


def test_moves_do_not_try_settled_pairs_again(monkeypatch):
    """One row of vertices that takes many rounds, beside 40 pairs that are settled at once and are then left alone."""
    tried = Counter()
    monkeypatch.setattr(kernels, "min", lambda *a, **k: (tried.update([frozenset(a[0])]) if k.get("key") else None) or min(*a, **k), raising=False)
    us, vs, ws = list(range(30)), list(range(1, 31)), [float(k + 1) for k in range(30)]
    pairs = [(100 + 2 * k, 101 + 2 * k) for k in range(40)]
    labels = kernels.moves(us + [a for a, _ in pairs], vs + [b for _, b in pairs], ws + [-1.0] * 40, {x: x for x in [*range(31), *(x for p in pairs for x in p)]})
    assert {labels[x] for x in range(31)} == {0} and all(labels[a] != labels[b] for a, b in pairs)
    assert all(tried[frozenset(p)] == 1 for p in pairs)


def _plain_moves(u, v, w, labels, local):
    """Moves as they are described: each step looks at all vertices, each prefix is searched through."""
    near, linked, lab = defaultdict(dict), defaultdict(set), dict(labels)
    for a, b, c, near_by in zip(u, v, w, local or [True] * len(u)):
        near[a][b] = near[b][a] = near[a].get(b, 0.0) + c
        if near_by:
            linked[a].add(b)
            linked[b].add(a)
    groups = lambda: {c: {x for x in lab if lab[x] == c} for c in set(lab.values())}
    pull = lambda x, s: sum(c for y, c in near[x].items() if y in s)

    def whole(s):
        seen, todo = set(list(s)[:1]), list(s)[:1]
        while todo:
            new = (linked[todo.pop()] & s) - seen
            seen |= new
            todo += new
        return seen == s

    def chain(a, b):
        a, b, free, total, best, steps, kept = set(a), set(b), set(a) | set(b), 0.0, 0.0, [], 0
        while free:
            gain = {x: pull(x, b) - pull(x, a) if x in a else pull(x, a) - pull(x, b) for x in free}
            x = min(free, key=lambda y: (-gain[y], y))
            if total + gain[x] + sum(g for g in gain.values() if g > 0) <= best + 1e-9:
                break
            free.discard(x)
            total += gain[x]
            steps.append((x, x in a))
            a, b = a ^ {x}, b ^ {x}
            if total > best + 1e-9 and (local is None or (whole(a) and whole(b))):
                best, kept = total, len(steps)
        return best, steps[:kept]

    fresh, improved = max(lab) + 1, True
    while improved:
        improved = False
        for p, q in sorted({tuple(sorted((lab[a], lab[b]))) for a, b in zip(u, v) if lab[a] != lab[b]}):
            of = groups()
            if p not in of or q not in of:
                continue
            between, (gain, steps) = sum(pull(x, of[q]) for x in of[p]), chain(of[p], of[q])
            if between > max(gain, 0) + 1e-9 and (local is None or whole(of[p] | of[q])):
                lab.update({x: p for x in of[q]})
                improved = True
            elif gain > 1e-9:
                lab.update({x: q if from_p else p for x, from_p in steps})
                improved = True
        for p in sorted(groups()):
            gain, steps = chain(groups()[p], set())
            if gain > 1e-9:
                lab.update({x: fresh if from_p else p for x, from_p in steps})
                fresh, improved = fresh + 1, True
    return {x: min(s) for s in groups().values() for x in s}


@pytest.mark.parametrize("seed", range(40))
def test_moves_are_those_of_a_plain_search(seed):
    """Lattices with far repulsions, more vertices than are looked at one by one."""
    rnd = random.Random(seed)
    n, across, lifted = rnd.randint(10, 40), rnd.randint(2, 6), seed % 2 == 0
    pairs = [(i, i + d) for i in range(n) for d in (1, across) if i + d < n and (d == across or (i + 1) % across)]
    far = [tuple(sorted(rnd.sample(range(n), 2))) for _ in range(2 * n)]
    u, v = zip(*pairs, *far)
    w = [float(rnd.randint(-2, 4)) if seed % 4 < 2 else rnd.uniform(-2, 4) for _ in pairs] + [float(rnd.randint(-4, 2)) for _ in far]
    local = [True] * len(pairs) + [False] * len(far)
    start = kernels.contraction(u[: len(pairs)], v[: len(pairs)], w[: len(pairs)], vertices=set(u) | set(v))
    assert kernels.moves(u, v, w, start, local=local if lifted else None) == _plain_moves(u, v, w, start, local if lifted else None)


def test_a_long_chain_is_not_searched_through_at_each_move(monkeypatch):
    """One cluster of 2,500 vertices that repulsions strain but none of whose prefixes holds together: few whole searches, no look at all vertices."""
    rnd, across = random.Random(3), 50
    n = across * across
    pairs = [(i, i + d) for i in range(n) for d in (1, across) if i + d < n and (d == across or (i + 1) % across)]
    far = [tuple(sorted(rnd.sample(range(n), 2))) for _ in range(3 * n)]
    u, v = zip(*pairs, *far)
    w, looked = [5.0] * len(pairs) + [-8.0] * len(far), Counter()
    monkeypatch.setattr(kernels, "min", lambda *a, **k: (looked.update(n=len(a[0])) if k.get("key") else None) or min(*a, **k), raising=False)
    meet = kernels._Side.connected
    monkeypatch.setattr(kernels._Side, "connected", lambda s: (looked.update(whole=s.ends is None and not s.apart and len(s.members) > n // 2) or meet(s)))
    kernels.moves(u, v, w, dict.fromkeys(range(n), 0), local=[True] * len(pairs) + [False] * len(far), most_rounds=1)
    assert looked["n"] <= n and looked["whole"] < 20
