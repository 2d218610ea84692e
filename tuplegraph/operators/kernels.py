"""Sequential searches and cluster growth on graphs that fit a task: plain functions on arrays, used by grouped maps.

They fix the order of steps that the distributed rounds are held against.
"""

from __future__ import annotations

import heapq
from collections import defaultdict
from itertools import count, product


class Adjacency:
    """In and out lists of a small graph; edges are (source, target, weight)."""

    def __init__(self, edges):
        self.into, self.out = defaultdict(list), defaultdict(list)
        for s, d, w in sorted(edges):
            self.out[s].append((d, w))
            self.into[d].append((s, w))
        self.pull = {v: sum(1 / w for _, w in near) for v, near in self.into.items()}
        self.push = {v: sum(1 / w for _, w in near) for v, near in self.out.items()}

    def nodes(self):
        return self.into.keys() | self.out.keys()


def distances(graph: Adjacency, origins, max_cost: float = float("inf"), start: float = 0.0):
    """Least cost from every node to the nearest origin, and the next node on the way."""
    best, way = {}, {}
    heap = [(start, o, None) for o in sorted(origins)]
    heapq.heapify(heap)
    while heap:
        cost, v, nxt = heapq.heappop(heap)
        if v in best:
            continue
        best[v], way[v] = cost, nxt
        for u, w in graph.into[v]:
            if u not in best and cost + w <= max_cost:
                heapq.heappush(heap, (cost + w, u, v))
    return best, way


def backward(graph: Adjacency, matches: dict, k: int, prestige: dict | None = None, origin_weight: bool = False, max_cost: float = float("inf"), per_root: int = 1, limit: int | None = None):
    """Backward expanding search: one reversed shortest-path iterator for each matched node, the nearest steps next.

    Gives answers {root, cost, leaves, edges} in the order in which their roots complete, and (touched, explored).
    With ``origin_weight``, an iterator starts at 1 / (1 + prestige) of its node instead of 0.
    """
    serial = count()
    heap, way, visited = [], {}, defaultdict(lambda: defaultdict(list))
    done, touched, explored, answers = set(), set(), 0, []
    for term in sorted(matches):
        for o in sorted(matches[term]):
            first = 1 / (1 + (prestige or {}).get(o, 0.0)) if origin_weight else 0.0
            heapq.heappush(heap, (first, o, next(serial), term, o, None))
            touched.add((term, o, o))
    while heap and len(answers) < (limit or k):
        cost, v, _, term, origin, nxt = heapq.heappop(heap)
        if (term, origin, v) in done:
            continue
        done.add((term, origin, v))
        way[term, origin, v] = nxt
        explored += 1
        if len(visited[v][term]) < per_root:
            visited[v][term].append((cost, origin))
            if len(visited[v]) == len(matches):
                others = [visited[v][t] if t != term else [(cost, origin)] for t in sorted(matches)]
                for combo in product(*others):
                    tree = _tree(v, [(t, o) for t, (_, o) in zip(sorted(matches), combo, strict=True)], lambda t, o, x: way[t, o, x], graph)
                    if _root_minimal(tree):
                        answers.append(tree)
        for u, w in graph.into[v]:
            if (term, origin, u) not in done and cost + w <= max_cost:
                touched.add((term, origin, u))
                heapq.heappush(heap, (cost + w, u, next(serial), term, origin, v))
    return answers, len({(t, v) for t, _, v in touched}), explored


def _root_minimal(tree):
    """Whether the root has two branches or holds a keyword."""
    kids = {c for p, c in tree["edges"] if p == tree["root"]}
    return len(kids) != 1 or tree["root"] in {v for _, v in tree["leaves"]}


def _tree(root, leaves, way, graph):
    """Union of the ways from a root; a way that meets the tree again keeps the first branch."""
    parent, weight = {root: None}, 0.0
    ends = []
    for t, o in leaves:
        v = root
        while (n := way(t, o, v)) is not None:
            if n not in parent:
                parent[n] = v
                weight += min(w for d, w in graph.out[v] if d == n)
            v = n
        ends.append((t, v))
    return {"root": root, "leaves": ends, "edges": sorted((p, c) for c, p in parent.items() if p is not None), "cost": weight, "nodes": sorted(parent)}


def bidirectional(graph: Adjacency, matches: dict, k: int, prestige: dict, mu: float = 0.5, combine: str = "max", max_explored: int = 10**9, limit: int | None = None, max_hops: int = 64):
    """Bidirectional search by spreading activation: an inward queue from the keywords, an outward queue of possible roots.

    Gives answers like ``backward``, best path for each (node, term), and (touched, explored).
    """
    terms = sorted(matches)
    dist, way = {t: {} for t in terms}, {t: {} for t in terms}
    act = {t: defaultdict(float) for t in terms}
    serial = count()
    inward, outward = [], []
    popped = {"in": set(), "out": set()}
    touched, explored, roots, minimal, done = set(), 0, {}, set(), set()

    def total(v):
        return sum(act[t][v] for t in terms)

    def push(queue, v):
        touched.add(v)
        heapq.heappush(queue, (-total(v), v, next(serial)))

    def settle(v):
        if all(v in dist[t] for t in terms):
            roots.setdefault(v, len(roots))
            ways = {way[t][v] for t in terms}
            (minimal.add if None in ways or len(ways) > 1 else minimal.discard)(v)

    def improve(t, v, cost, nxt):
        """A shorter way to a term; it goes on over every edge that was explored from either end, or leads to a known node."""
        heap = [(cost, v, nxt)]  # least first, so that a node improves once in a call
        while heap:
            c, x, n = heapq.heappop(heap)
            if c >= dist[t].get(x, float("inf")) - 1e-12:
                continue
            dist[t][x], way[t][x] = c, n
            settle(x)
            for u, w in graph.into[x]:
                seen = u in dist[t] or x in popped["in"] or u in popped["out"]
                if seen and c + w < dist[t].get(u, float("inf")) - 1e-12:
                    heapq.heappush(heap, (c + w, u, x))

    for t in terms:
        for o in sorted(matches[t]):
            act[t][o] = max(act[t][o], prestige.get(o, 0.0) / len(matches[t]))
            dist[t][o], way[t][o] = 0.0, None
    for o in sorted({o for t in terms for o in matches[t]}):
        settle(o)
        push(inward, o)
    wanted = limit or k
    while (inward or outward) and len(minimal) < wanted and explored < max_explored:
        use_in = bool(inward) and (not outward or -inward[0][0] >= -outward[0][0])
        side = "in" if use_in else "out"
        _, v, _ = heapq.heappop(inward if use_in else outward)
        if v in popped[side]:
            continue
        popped[side].add(v)
        if v not in done:
            explored += 1
            done.add(v)
        near = graph.into[v] if use_in else graph.out[v]
        scale = (graph.pull if use_in else graph.push).get(v, 1.0)
        for u, w in near:
            for t in terms:
                if use_in and v in dist[t]:
                    improve(t, u, dist[t][v] + w, v)
                elif not use_in and u in dist[t]:
                    improve(t, v, dist[t][u] + w, u)
                given = mu * act[t][v] * (1 / w) / scale
                act[t][u] = max(act[t][u], given) if combine == "max" else act[t][u] + given
            if u not in popped[side]:
                push(inward if use_in else outward, u)
        for t in terms:  # a node keeps what it does not pass on
            act[t][v] *= 1 - mu
        if use_in and v not in popped["out"]:
            push(outward, v)
    answers = [_tree(r, [(t, None) for t in terms], lambda t, o, x: way[t][x], graph) for r in sorted(minimal, key=roots.get)]
    return answers, len(touched), explored


def steiner(graph: Adjacency, matches: dict):
    """Least total weight of a rooted tree that reaches a node of every term, and its root: dynamic programme over term sets."""
    terms = sorted(matches)
    full = (1 << len(terms)) - 1
    best = defaultdict(dict)
    for i, t in enumerate(terms):
        best[1 << i] = dict(distances(graph, matches[t])[0])
    for mask in range(1, full + 1):
        cost = best[mask]
        part = (mask - 1) & mask
        while part:
            for v, c in best[part].items():
                if v in best[mask ^ part]:
                    cost[v] = min(cost.get(v, float("inf")), c + best[mask ^ part][v])
            part = (part - 1) & mask
        heap = [(c, v) for v, c in cost.items()]
        heapq.heapify(heap)
        while heap:
            c, v = heapq.heappop(heap)
            if c > cost[v]:
                continue
            for u, w in graph.into[v]:
                if c + w < cost.get(u, float("inf")):
                    cost[u] = c + w
                    heapq.heappush(heap, (c + w, u))
    if not best[full]:
        return None
    return min((c, v) for v, c in best[full].items())


# ---- clusters ----


def grow(graph: Adjacency, nodes, size: int, technique: str, order, scan: str = "members", prefer: dict | None = None, back: dict | None = None) -> dict:
    """Cluster of each node (its seed), grown one after another from seeds in the given order.

    connection: any free neighbour of a member, smallest first. ratio: the free neighbour whose two edge weights are most
    alike. diameter: the free neighbour that adds least to the largest distance in the cluster. ball: all neighbours of the
    seed, then those of the member nearest to it, and so on.
    """
    free, cluster = set(nodes), {}
    both = {v: sorted({u for u, _ in graph.out[v]} | {u for u, _ in graph.into[v]}) for v in nodes}
    weight = {(s, d): w for s in graph.out for d, w in graph.out[s]}

    def ratio(u, v):
        a, b = weight.get((u, v)), weight.get((v, u))
        return float("inf") if a is None or b is None else max(a, b) / min(a, b)

    def near(u, v):
        return min(weight.get((u, v), float("inf")), weight.get((v, u), float("inf")))

    for seed in order:
        if seed not in free:
            continue
        members = [seed]
        free.discard(seed)
        cluster[seed] = seed
        if technique == "ball":
            heap, reach = [(0.0, seed)], {seed: 0.0}
            while heap and len(members) < size:
                c, v = heapq.heappop(heap)
                for u in both[v]:
                    if u in free and len(members) < size:
                        free.discard(u)
                        members.append(u)
                        cluster[u] = seed
                        reach[u] = c + near(v, u)
                        heapq.heappush(heap, (reach[u], u))
            continue
        apart = {(seed, seed): 0.0}
        while len(members) < size:
            options = []
            for v in members if scan == "members" else [seed]:
                for u in both[v]:
                    if u in free:
                        if technique == "connection":
                            options.append((0.0, u))
                        elif technique == "ratio":
                            options.append((ratio(v, u), u))
                        else:
                            far = max(min(apart[m, x] + near(x, u) for x in members) for m in members)
                            options.append((far, u))
            if not options:
                break
            _, u = min(options)
            if technique == "diameter":
                for m in members:
                    apart[m, u] = apart[u, m] = min(apart[m, x] + near(x, u) for x in members)
                apart[u, u] = 0.0
            free.discard(u)
            members.append(u)
            cluster[u] = seed
    return cluster


def by_activation(graph: Adjacency, activation: dict, page: int, mu: float = 0.5) -> dict:
    """Clusters filled in order of activation: the most activated node first, each pick spreads to its neighbours."""
    act = dict(activation)
    heap = [(-a, v) for v, a in act.items()]
    heapq.heapify(heap)
    cluster, members, current = {}, 0, None
    while heap:
        a, v = heapq.heappop(heap)
        if v in cluster or -a < act[v] - 1e-12:
            continue
        if current is None or members >= page:
            current, members = v, 0
        cluster[v] = current
        members += 1
        for u, w in graph.into[v]:
            if u not in cluster:
                given = mu * act[v] * (1 / w) / graph.pull[v]
                if given > act.get(u, 0.0):
                    act[u] = given
                    heapq.heappush(heap, (-given, u))
    return cluster


def all_pairs(nodes, edges) -> dict:
    """Least costs between all ordered pairs of a small graph."""
    graph = Adjacency([(d, s, w) for s, d, w in edges])
    return {(a, b): c for a in nodes for b, c in distances(graph, [a])[0].items()}
